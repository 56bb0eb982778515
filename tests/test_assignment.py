import itertools

import numpy as np
import pytest

from twoview.operators import assignment as A
from twoview.operators.model import CodeModel, ModelSpec, pack_words, unpack_words


def cube(b):
    return np.array([[i >> s & 1 for s in range(b)] for i in range(1 << b)], float)


@pytest.mark.parametrize("b", [2, 3, 4, 5, 6])
def test_moments_and_isometries(b):
    rng = np.random.default_rng(b)
    k = 1 << b
    pi = rng.permutation(k)
    h = A.hamming_table(k)[np.ix_(pi, pi)]
    assert h.mean() == b / 2 and h.var() == b / 4
    c = rng.normal(size=(k, 3))
    f = A.hamming_scale(A.centroid_distances(c), b)
    assert np.isclose(f.mean(), b / 2) and np.isclose(f.var(), b / 4)
    for loss in (A.DistanceLoss(c, b), A.RankLoss(c, b)):
        base = loss.full(pi)
        assert np.isclose(loss.full(pi ^ 1), base)
        swapped = (pi & ~3) | (pi & 1) << 1 | (pi & 2) >> 1
        assert np.isclose(loss.full(swapped), base)


def test_known_optimum():
    """Centroids on the cube's vertices: the identity is best among all numberings."""
    for b, plain, weighted in ((2, 0.645072, 0.317207), (3, 5.221751, 3.578836)):
        c = cube(b)
        d = A.centroid_distances(c)
        assert A.loss_rank(np.arange(1 << b), d, A.pair_weights(d)) == 0
        assert np.isclose(A.loss_distance(np.arange(1 << b), A.hamming_scale(A.centroid_distances(c, True), b)), 0)
        assert np.isclose(A.DistanceLoss(c, b, None).full(np.arange(1 << b)), plain, atol=1e-6)
        assert np.isclose(A.DistanceLoss(c, b).full(np.arange(1 << b)), weighted, atol=1e-6)
    loss = A.DistanceLoss(cube(2), 2)
    assert min(loss.full(np.array(p)) for p in itertools.permutations(range(4))) >= loss.full(np.arange(4)) - 1e-9


@pytest.mark.parametrize("b", [2, 3, 4])
def test_swap_changes_match_whole_losses(b):
    rng = np.random.default_rng(7)
    k = 1 << b
    c = rng.normal(size=(k, 2))
    c[1] = c[0]  # equal centroids
    for loss in (A.DistanceLoss(c, b), A.RankLoss(c, b), A.RankLoss(c, b, "knn", 3)):
        pi = rng.permutation(k)
        loss.start(pi)
        for i in range(k):
            for j in range(k):
                if i != j:
                    new = pi.copy()
                    new[i], new[j] = pi[j], pi[i]
                    assert np.isclose(loss.delta(pi, i, j), loss.full(new) - loss.full(pi), atol=1e-9)


def test_incremental_state_survives_many_swaps():
    rng = np.random.default_rng(1)
    loss = A.RankLoss(rng.normal(size=(16, 3)), 4)
    got = A.anneal(loss, 16, n_iter=800, seed=2)
    assert np.isclose(loss.value, loss.full(got.last)) and sorted(got.last) == list(range(16))


def test_disagreement_by_definition():
    rng = np.random.default_rng(3)
    c, pi = rng.integers(0, 3, (8, 2)).astype(float), rng.permutation(8)
    d, h = A.centroid_distances(c), A.hamming_table(8)[np.ix_(pi, pi)]
    want = [[sum(d[i, j] < d[i, k] and h[i, j] > h[i, k] for k in range(8)) for j in range(8)] for i in range(8)]
    assert A.rank_disagreement(pi, d).tolist() == want


def test_anneal_and_greedy():
    rng = np.random.default_rng(5)
    c = rng.normal(size=(16, 4))
    loss = A.DistanceLoss(c, 4)
    a, b = A.anneal(loss, 16, n_iter=4000, seed=1, trace_every=500), A.anneal(loss, 16, n_iter=4000, seed=1)
    assert a.best.tolist() == b.best.tolist() and a.best_loss <= a.first_loss and len(a.trace) == 9
    assert A.anneal(loss, 16, n_iter=500, accept="metropolis").best_loss <= a.first_loss
    for hood in ("index_pairs", "bit_neighbours"):
        pi, value, _ = A.greedy_switch(loss, 16, neighbourhood=hood)
        assert value <= a.first_loss
    pi, value, _ = A.greedy_switch(loss, 16)
    loss.start(pi)
    assert all(loss.delta(pi, i, j) >= -1e-9 for i in range(16) for j in range(i))
    assert min(A.anneal(loss, 16, n_iter=60_000, seed=s).best_loss for s in range(3)) <= value + 1e-6


def test_harmonic_and_rank_rules():
    w = A.harmonic_weights(6)
    assert (np.diff(w) > 0).all() and (np.diff(w, 2) < 0).all()
    d = A.centroid_distances(np.array([[0.0], [1.0], [3.0]]))
    assert A.pair_weights(d)[0].tolist() == [0, 1, 0.5]
    assert A.pair_weights(d, rank_rule="as_printed")[0].tolist() == [0, 1, 1]
    assert -1 <= A.kendall_tau(np.arange(3), d) <= 1


@pytest.mark.parametrize("M,b", [(16, 4), (32, 4), (8, 8), (20, 8), (6, 4), (5, 3), (64, 1), (70, 1)])
def test_words_round_trip(M, b):
    spec = ModelSpec(M * 2, M, b)
    codes = np.random.default_rng(0).integers(0, spec.K, (50, M))
    codes[0] = spec.K - 1
    words = pack_words(codes, spec)
    assert words.shape == (50, spec.n_words) and unpack_words(words, spec).tolist() == codes.tolist()
    assert spec.code_bytes == -(-M * b // 8)


def test_relabelling_needs_a_bijection():
    m = CodeModel(ModelSpec(4, 2, 1), np.zeros((2, 2, 2)))
    with pytest.raises(ValueError):
        m.relabelled(np.zeros((2, 2), int), "x")
