"""Which number each centroid gets: objectives over numberings, and ways to improve them by swaps.

pi[i] is the number of centroid i, one slice at a time. Nothing here depends on the number of vectors.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession

from twoview.operators.model import CodeModel


def centroid_distances(c: np.ndarray, squared: bool = False) -> np.ndarray:
    """Distances between the rows of c."""
    d = c[:, None] - c[None]
    d2 = np.einsum("ijk,ijk->ij", d, d)
    return d2 if squared else np.sqrt(d2)


def hamming_scale(dist: np.ndarray, b: int, include_self: bool = True) -> np.ndarray:
    """Distances moved and stretched to the mean b/2 and variance b/4 that Hamming distances over the whole cube have."""
    pick = dist if include_self else dist[~np.eye(len(dist), dtype=bool)]
    mean, std = pick.mean(), pick.std()
    return np.full_like(dist, b / 2) if std == 0 else b / 2 + (dist - mean) * (np.sqrt(b) / 2 / std)


def hamming_table(k: int) -> np.ndarray:
    n = np.arange(k, dtype=np.uint32)
    return np.bitwise_count(n[:, None] ^ n[None]).astype(np.int64)


def near_weights(scaled: np.ndarray, alpha: float | None = 0.5) -> np.ndarray:
    """alpha to the power of the scaled distance, so that near pairs count more; None: all alike."""
    return np.ones_like(scaled) if alpha is None else alpha**scaled


def loss_distance(pi: np.ndarray, scaled: np.ndarray, weight: np.ndarray | None = None) -> float:
    """Weighted square differences between Hamming and scaled distances over ordered pairs."""
    h = hamming_table(len(pi))[np.ix_(pi, pi)]
    return float((np.ones_like(scaled) if weight is None else weight).ravel() @ ((h - scaled) ** 2).ravel())


def delta_distance(pi: np.ndarray, i: int, j: int, scaled: np.ndarray, weight: np.ndarray, cube: np.ndarray) -> float:
    """Change of loss_distance when i and j trade numbers: only their pairs with others matter."""
    hi, hj = cube[pi[i], pi], cube[pi[j], pi]
    gain = weight[i] * ((hj - scaled[i]) ** 2 - (hi - scaled[i]) ** 2) + weight[j] * ((hi - scaled[j]) ** 2 - (hj - scaled[j]) ** 2)
    gain[[i, j]] = 0
    return 2 * float(gain.sum())


def loss_channel(pi: np.ndarray, dist: np.ndarray) -> float:
    """What one flipped bit costs: squared distance summed over pairs whose numbers differ in one bit."""
    h = hamming_table(len(pi))[np.ix_(pi, pi)]
    return float((dist**2)[h == 1].sum())


def rank_disagreement(pi: np.ndarray, dist: np.ndarray) -> np.ndarray:
    """For each (i, j), how many k are truly farther from i than j but nearer in Hamming distance.

    For each i, centroids are taken from far to near in groups of equal distance; a histogram of the Hamming values
    of all farther ones gives the counts.
    """
    k = len(pi)
    h = hamming_table(k)[np.ix_(pi, pi)]
    return np.stack([_disagreement_row(dist[i], h[i]) for i in range(k)])


def _disagreement_row(dist: np.ndarray, h: np.ndarray) -> np.ndarray:
    k, bits = len(dist), int(h.max()) + 1
    order = np.argsort(-dist, kind="stable")
    d, hs = dist[order], h[order]
    one = np.zeros((k + 1, bits + 1), np.int64)
    one[np.arange(1, k + 1), hs + 1] = 1
    below = np.cumsum(np.cumsum(one, 0), 1)  # below[t, v]: among the first t, those with Hamming value under v
    first = np.searchsorted(-d, -d, "left")
    out = np.empty(k, np.int64)
    out[order] = below[first, hs]
    return out


def harmonic_weights(k: int) -> np.ndarray:
    """0, 1, 1 + 1/2, ...: grows ever slower."""
    return np.append(0.0, np.cumsum(1 / np.arange(1, k + 1)))


def pair_weights(dist: np.ndarray, pairs: str = "all", k: int = 8, rank_rule: str = "nearest_first") -> np.ndarray:
    """Weight of each (i, j): one over j's rank among i's neighbours ('all'), or one for the k nearest ('knn')."""
    n = len(dist)
    off = ~np.eye(n, dtype=bool)
    if pairs == "knn":
        order = np.argsort(dist + np.where(off, 0, np.inf), axis=1, kind="stable")
        out = np.zeros_like(dist)
        np.put_along_axis(out, order[:, :k], 1.0, 1)
        return out * off
    closer = (dist[:, None, :] < dist[:, :, None]).sum(2) if rank_rule == "nearest_first" else (dist[:, None, :] > dist[:, :, None]).sum(2)
    return off / np.maximum(closer, 1)


def loss_rank(pi: np.ndarray, dist: np.ndarray, weight: np.ndarray) -> float:
    """Harmonic weight of each pair's disagreement, times the pair's weight."""
    return float((weight * harmonic_weights(len(pi))[rank_disagreement(pi, dist)]).sum())


def kendall_tau(pi: np.ndarray, dist: np.ndarray) -> float:
    """Concordant less discordant triples (i; j, k), over all triples that neither side ties."""
    h = hamming_table(len(pi))[np.ix_(pi, pi)]
    a = np.sign(dist[:, :, None] - dist[:, None, :])
    b = np.sign(h[:, :, None] - h[:, None, :])
    both = (a != 0) & (b != 0)
    return float((a * b).sum() / max(both.sum(), 1))


class DistanceLoss:
    """The distance objective with O(K) updates."""

    def __init__(self, centroids: np.ndarray, b: int, alpha: float | None = 0.5) -> None:
        self.scaled = hamming_scale(centroid_distances(centroids), b)
        self.weight = near_weights(self.scaled, alpha)
        self.cube = hamming_table(len(centroids))
        self.rows = self.cube.astype(float)
        self.pull = 2 * self.weight * self.scaled

    def full(self, pi: np.ndarray) -> float:
        return loss_distance(pi, self.scaled, self.weight)

    def start(self, pi: np.ndarray) -> None:
        pass

    def delta(self, pi: np.ndarray, i: int, j: int) -> float:
        """delta_distance with the squares multiplied out, which leaves few steps over one row."""
        hi, hj = self.rows[pi[i]][pi], self.rows[pi[j]][pi]
        gap = hj - hi
        gap[i] = gap[j] = 0.0
        hi += hj
        hi *= self.weight[i] - self.weight[j]
        hi -= self.pull[i] - self.pull[j]
        return 2 * float(gap @ hi)

    def accept(self) -> None:
        pass


class RankLoss:
    """The ranking objective; a swap changes two columns of every row, and two whole rows."""

    def __init__(self, centroids: np.ndarray, b: int, pairs: str = "all", k: int = 8, rank_rule: str = "nearest_first") -> None:
        self.dist = centroid_distances(centroids)
        self.weight = pair_weights(self.dist, pairs, k, rank_rule)
        self.cube = hamming_table(len(centroids))
        self.concave = harmonic_weights(len(centroids))
        self.farther = self.dist[:, None, :] > self.dist[:, :, None]  # i, j, k: k farther from i than j

    def full(self, pi: np.ndarray) -> float:
        return loss_rank(pi, self.dist, self.weight)

    def start(self, pi: np.ndarray) -> None:
        self.counts = rank_disagreement(pi, self.dist)
        self.value = float((self.weight * self.concave[self.counts]).sum())

    def delta(self, pi: np.ndarray, i: int, j: int) -> float:
        h = self.cube[np.ix_(pi, pi)]
        counts = self.counts.copy()
        hi, hj = h[:, i].copy(), h[:, j].copy()
        swapped = np.flatnonzero(hi != hj)
        rows = swapped[(swapped != i) & (swapped != j)]
        if len(rows):
            sub, far = h[rows], self.farther[rows]
            a, c = hi[rows, None], hj[rows, None]
            counts[rows] += far[:, :, i] * ((sub > c).astype(int) - (sub > a)) + far[:, :, j] * ((sub > a).astype(int) - (sub > c))
            new = sub.copy()
            new[:, i], new[:, j] = hj[rows], hi[rows]
            for col in (i, j):
                counts[rows, col] = (far[:, col, :] & (new < new[:, col, None])).sum(1)
        new_pi = pi.copy()
        new_pi[i], new_pi[j] = pi[j], pi[i]
        for row in (i, j):
            counts[row] = _disagreement_row(self.dist[row], self.cube[new_pi[row], new_pi])
        value = float((self.weight * self.concave[counts]).sum())
        self._next = (counts, value)
        return value - self.value

    def accept(self) -> None:
        self.counts, self.value = self._next


@dataclass
class Annealed:
    """Best and last numbering, their losses, and the trace (iteration, temperature, loss, accepted)."""

    best: np.ndarray
    best_loss: float
    last: np.ndarray
    last_loss: float
    first_loss: float
    trace: list[tuple[int, float, float, int]]
    snapshots: dict[int, np.ndarray]


def anneal(
    loss: DistanceLoss | RankLoss, k: int, *, n_iter: int = 500_000, t0: float = 0.7, decay: float = 0.9 ** (1 / 500), seed: int = 0, accept: str = "fixed",
    trace_every: int = 0, snapshots: tuple[int, ...] = (), recompute: int = 10_000, start: np.ndarray | None = None,
) -> Annealed:
    """Random swaps from the identity: those that lower the loss are taken, others with a chance that shrinks step by step.

    accept 'fixed': that chance is the temperature itself; 'metropolis': it also falls with the loss's rise.
    """
    rng = np.random.default_rng(seed)
    pi = np.arange(k) if start is None else start.copy()
    loss.start(pi)
    value = first = loss.full(pi)
    best, best_value, t, taken = pi.copy(), value, t0, 0
    trace: list[tuple[int, float, float, int]] = [(0, t0, value, 0)] if trace_every else []
    kept = {0: pi.copy()} if 0 in snapshots else {}
    for block in range(0, n_iter, 4096):
        n = min(4096, n_iter - block)
        left, right = rng.integers(0, k, n), rng.integers(0, k - 1, n)
        right = right + (right >= left)
        luck = rng.random(n)
        for s in range(n):
            i, j = int(left[s]), int(right[s])
            d = loss.delta(pi, i, j)
            chance = t if accept == "fixed" else t * np.exp(-d / max(abs(first) * t, 1e-300))
            if d < 0 or luck[s] < chance:
                pi[i], pi[j] = pi[j], pi[i]
                loss.accept()
                value += d
                taken += 1
                if value < best_value - 1e-12:
                    best, best_value = pi.copy(), value
            t *= decay
            it = block + s + 1
            if it % recompute == 0:
                value = loss.full(pi)
            if trace_every and it % trace_every == 0:
                trace.append((it, t, value, taken))
            if it in snapshots:
                kept[it] = best.copy()
    return Annealed(best, loss.full(best), pi, loss.full(pi), first, trace, kept)


def greedy_switch(loss: DistanceLoss | RankLoss, k: int, *, neighbourhood: str = "index_pairs", max_rounds: int = 10_000, start: np.ndarray | None = None) -> tuple[np.ndarray, float, int]:
    """The best improving swap round after round, until there is none; pairs of all numbers, or of those one bit apart."""
    pi = np.arange(k) if start is None else start.copy()
    loss.start(pi)
    rounds = 0
    while rounds < max_rounds:
        inverse = np.argsort(pi)
        if neighbourhood == "index_pairs":
            pairs = [(i, j) for i in range(k) for j in range(i + 1, k)]
        else:
            pairs = [(int(inverse[c]), int(inverse[c ^ (1 << s)])) for c in range(k) for s in range(k.bit_length() - 1) if not c >> s & 1]
        deltas = [loss.delta(pi, i, j) for i, j in pairs]
        best = int(np.argmin(deltas)) if pairs else 0
        if not pairs or deltas[best] >= -1e-12:
            break
        i, j = pairs[best]
        loss.delta(pi, i, j)
        loss.accept()
        pi[i], pi[j] = pi[j], pi[i]
        rounds += 1
    return pi, loss.full(pi), rounds


def gray(k: int) -> np.ndarray:
    """A fixed numbering in which successive centroids differ in one bit."""
    i = np.arange(k)
    return i ^ (i >> 1)


def affine(k: int) -> np.ndarray:
    """A fixed numbering without order."""
    return (5 * np.arange(k) + 3) % k


def make_loss(centroids: np.ndarray, b: int, construction: str, alpha: float | None = 0.5) -> DistanceLoss | RankLoss:
    if construction == "dist_assigned":
        return DistanceLoss(centroids, b, alpha)
    if construction == "rank_assigned":
        return RankLoss(centroids, b)
    raise ValueError(f"no objective for {construction}")


def fit_assignment(
    spark: SparkSession, model: CodeModel, construction: str = "dist_assigned", *, alpha: float | None = 0.5, n_iter: int = 500_000, restarts: int = 1, seed: int = 0,
    optimizer: str = "anneal", trace_every: int = 0, snapshots: tuple[int, ...] = (),
) -> tuple[CodeModel, pd.DataFrame]:
    """Renumber a model: one task for each slice and restart, the best restart of each slice wins.

    Returns the renumbered model and the trace (m, restart, iter, temperature, loss, accepted, seconds; the last row of
    each run is its end). The model's info has the loss, the seconds of all runs together, and at each of
    the snapshots the best numberings up to there.
    """
    spec, book = model.spec, model.codebook
    sent = spark.sparkContext.broadcast(book)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for m, r in zip(pdf["m"], pdf["restart"], strict=True):
                loss = make_loss(sent.value[m], spec.b, construction, alpha)
                s = seed * 1_000_003 + int(m) * 101 + int(r)
                began, shots = time.perf_counter(), {}
                if optimizer == "greedy":
                    begin = np.arange(spec.K) if r == 0 else np.random.default_rng(s).permutation(spec.K)
                    first = loss.full(begin)
                    pi, value, rounds = greedy_switch(loss, spec.K, start=begin)
                    trace = [(0, 0.0, first, 0), (rounds, 0.0, value, rounds)]
                else:
                    got = anneal(loss, spec.K, n_iter=n_iter, seed=s, trace_every=trace_every, snapshots=snapshots)
                    shots = got.snapshots
                    pi, value, trace = got.best, got.best_loss, [*(got.trace or [(0, 0.7, got.first_loss, 0)]), (n_iter, 0.0, got.best_loss, 0)]
                took = time.perf_counter() - began
                ends = [(m, r, -1, 0.0, value, 0, took, pi.tolist())] + [(m, r, -2 - it, 0.0, loss.full(p), 0, took, p.tolist()) for it, p in shots.items()]
                yield pd.DataFrame([(m, r, it, t, v, a, took, None) for it, t, v, a in trace] + ends, columns=["m", "restart", "iter", "temperature", "loss", "accepted", "seconds", "pi"])

    grid = spark.range(spec.M * restarts).selectExpr(f"cast(id % {spec.M} as int) m", f"cast(id div {spec.M} as int) restart").repartition(spec.M * restarts, "m", "restart")
    rows = grid.mapInPandas(run, "m int, restart int, iter bigint, temperature double, loss double, accepted bigint, seconds double, pi array<int>").toPandas()
    ends = rows[rows["iter"] == -1].sort_values(["m", "loss", "restart"]).groupby("m").first()
    out = model.relabelled(np.stack([np.array(ends.loc[m, "pi"]) for m in range(spec.M)]), construction)
    out.info["loss"] = float(ends["loss"].sum())
    out.info["seconds"] = float(rows.loc[rows["iter"] == -1, "seconds"].sum())
    won = rows.set_index(["m", "restart", "iter"])["pi"] if snapshots else None
    out.info["snapshots"] = {it: np.stack([np.array(won.loc[(m, int(ends.loc[m, "restart"]), -2 - it)]) for m in range(spec.M)]) for it in snapshots}
    return out, rows[rows["iter"] >= 0].drop(columns="pi").reset_index(drop=True)


LossMaker = Callable[[np.ndarray], DistanceLoss | RankLoss]
