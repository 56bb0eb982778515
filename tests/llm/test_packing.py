import itertools
import random

import numpy as np

from twoview.llm import packing as P


def test_bounds_are_optimal():
    rng = random.Random(3)
    for _ in range(30):
        n = rng.randrange(1, 9)
        length = np.array(sorted(rng.sample(range(1, 60), n)))
        count = np.array([rng.randrange(1, 9) for _ in range(n)])
        for buckets in (1, 2, 3, 12):
            best = min(
                sum(c * (min(b for b in cut if b >= x) - x) for x, c in zip(length, count, strict=True))
                for k in range(1, min(buckets, n) + 1)
                for rest in itertools.combinations(length[:-1].tolist(), k - 1)
                for cut in [[*rest, int(length[-1])]]
            )
            bounds, waste = P.best_bounds(length, count, length * count, buckets)
            assert waste == best and len(bounds) <= buckets and bounds[-1] == length[-1]
            assert waste == sum(c * (min(b for b in bounds if b >= x) - x) for x, c in zip(length, count, strict=True))


def test_batches_fill_the_budget(spark):
    rng = random.Random(5)
    texts = ["w " * rng.randrange(0, 120) for _ in range(400)] + [None, "", "x " * 5000]
    docs = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)] + [(None, "a b", 2), (3, "again", 3)], "doc_id long, text string, bucket int")
    out = P.pack_documents(docs, buckets=4, budget=256).collect()
    assert len(out) == len(texts) + 2
    groups = {}
    for r in out:
        assert r.n_tokens <= r.pad_to
        groups.setdefault((r.bucket, r.batch), []).append(r)
    last = {}
    for (b, k), rows in groups.items():
        last[b] = max(last.get(b, 0), k)
        cap = max(1, 256 // rows[0].pad_to)
        assert sorted(r.place for r in rows) == list(range(len(rows))) and len(rows) <= cap
    assert all(len(rows) == max(1, 256 // rows[0].pad_to) for (b, k), rows in groups.items() if k < last[b])
    assert {r.doc_id: r.n_tokens for r in out}[402] == 5001 and {r.doc_id: r.n_tokens for r in out}[400] == 1
    assert P.pack_documents(docs.limit(0)).count() == 0


def test_halving_finds_what_trying_all_cuts_finds():
    rng = np.random.default_rng(2)
    for n, buckets in ((1, 3), (2, 1), (40, 5), (300, 16), (300, 1)):
        length = np.sort(rng.choice(30_000, n, replace=False)) + 1
        count = rng.integers(1, 1000, n)
        best = np.append(0.0, np.full(n, np.inf))
        c, t = np.append(0, np.cumsum(count)), np.append(0, np.cumsum(count * length))
        for _ in range(min(buckets, n)):
            best = np.array([0.0] + [min(best[i] + length[j - 1] * (c[j] - c[i]) - (t[j] - t[i]) for i in range(j)) for j in range(1, n + 1)])
        assert P.best_bounds(length, count, count * length, buckets)[1] == best[n]


def test_whole_query_against_brute_force(spark):
    """Buckets, batches and places of the given table, computed row by row."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = sorted((r.doc_id, len((r.text or "").split()) + 1) for r in docs.select("doc_id", "text").collect())
    lengths, counts = np.unique([n for _, n in rows], return_counts=True)
    bounds, _ = P.best_bounds(lengths, counts, lengths * counts, 16)
    seen, want = {}, {}
    for i, n in rows:
        k = next(k for k, b in enumerate(bounds) if n <= b)
        held = max(1, 16_384 // bounds[k])
        at = seen[k] = seen.get(k, -1) + 1
        want[i] = (n, k, bounds[k], at // held, at % held)
    assert {r.doc_id: tuple(r)[1:] for r in P.pack_documents(docs).collect()} == want
