import random
from fractions import Fraction

import duckdb
import pytest

from twoview.llm import mixing as M


def test_schedule_keeps_within_one_block():
    for parts in ([1], [3, 1], [500, 300, 150, 50], [7] * 30, [970] + [1] * 30, [333, 333, 334], [999, 1]):
        period, done = sum(parts), [0] * len(parts)
        order = M.fair_schedule(parts)
        assert len(order) == period
        for t, (i, nth) in enumerate(order):
            assert nth == done[i]
            done[i] += 1
            assert all(abs(d - q * (t + 1) / period) < 1 for d, q in zip(done, parts, strict=True))
        assert done == parts


def test_quotas():
    assert M.quotas({"a": 1.0, "b": 3.0}, 100) == [("b", 75), ("a", 25)] or sum(q for _, q in M.quotas({"a": 1.0, "b": 3.0}, 100)) == 100
    assert dict(M.quotas({"a": 0.0, "b": 1.0}, 10)) == {"a": 1, "b": 9}
    with pytest.raises(ValueError):
        M.quotas({str(i): 1.0 for i in range(11)}, 10)


def test_all_rows_in_order(spark):
    rows = [(i, f"s{min(i % 7, 2)}", "t") for i in range(500)] + [(1000, None, None), (None, "s0", "x"), (5, "s5", "y"), (5, "it's \\ odd", "z")]
    docs = spark.createDataFrame(rows, "doc_id long, source string, block string")
    out = M.mix_sources(docs, block_rows=4, period=50).collect()
    assert len(out) == len(rows)
    per = {}
    for r in sorted(out, key=lambda r: (r.slot, r.place)):
        per.setdefault(r.source, []).append(r)
    for got in per.values():
        assert [x.block * 4 + x.place for x in got] == list(range(len(got)))
        ids = [-1 if x.doc_id is None else x.doc_id for x in got]
        assert ids == sorted(ids)
    slots = {}
    for r in out:
        assert slots.setdefault(r.slot, (r.source, r.block)) == (r.source, r.block)
    assert M.mix_sources(docs.limit(0)).count() == 0


def test_matches_sql(spark):
    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{d}/documents.parquet'")
    cols = ["doc_id", "source", "block", "slot", "place", "target"]
    want = sorted(con.execute(f"SELECT {', '.join(cols)} FROM ({M.oracle()})").fetchall())
    got = sorted(tuple(r) for r in M.mix_sources(spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "source")).select(*cols).collect())
    assert got == want


def test_plan_has_no_python(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    plan = M.mix_sources(docs)._jdf.queryExecution().executedPlan().toString()
    assert not any(x in plan for x in ("Python", "Pandas", "Arrow", "ExistingRDD"))


def test_exact_weights_never_drift():
    rng = random.Random(3)
    cases = [{"a": 0.5} | {f"s{i}": 0.5 / 9 for i in range(9)}, {"a": 1.0}, {"a": 0.34, "b": 0.33, "c": 0.32, "d": 0.01}, {str(i): 1.6**i for i in range(30)}]
    cases += [{str(i): rng.random() ** 3 + 1e-6 for i in range(n)} for n in (2, 7, 1500)]
    for weights in cases:
        way, total = M.paths(M.whole_weights(weights)), sum(map(Fraction, weights.values()))
        for first in (0, 10**6, 10**9):  # slots, far over many periods of 1000
            taken = {}
            for s, w in weights.items():
                share = Fraction(w) / total
                i = max(0, int(first * share) - 2)
                while (slot := M.slot_of(i, way[s])) < first + 300:
                    assert abs(i + 1 - share * (slot + 1)) < 2 and abs(i - share * slot) < 2
                    assert taken.setdefault(slot, s) == s
                    i += 1
            assert all(k in taken for k in range(first, first + 300))


def test_given_weights_are_the_target(spark):
    rows = [(i, "a" if i < 6000 else f"s{i % 9}") for i in range(12000)] + [(20000, None), (20001, "z")]
    docs = spark.createDataFrame(rows, "doc_id long, source string")
    weights = {"a": 0.5} | {f"s{i}": 0.5 / 9 for i in range(9)}
    out = M.mix_sources(docs, weights, block_rows=1).collect()
    way = M.paths(M.whole_weights(weights))
    assert len({r.slot for r in out}) == len(out) == len(rows)
    assert all(r.slot == M.slot_of(r.block, way[r.source]) and abs(r.target - weights[r.source]) < 1e-12 for r in out if r.source in weights)
    assert all(abs(r.block - r.slot / 2) < 2 for r in out if r.source == "a")
    last = max(r.slot for r in out if r.source in weights)
    assert sorted((r.slot, r.source, r.target) for r in out if r.source not in weights) == [(last + 1, None, 0.0), (last + 2, "z", 0.0)]


def test_more_sources_than_a_period(spark):
    docs = spark.range(3000).selectExpr("id AS doc_id", "concat('s', id % 1200) AS source")
    out = M.mix_sources(docs, block_rows=1).collect()
    assert len({r.slot for r in out}) == len(out) == 3000
    assert all(abs(r.block + 1 - r.target * (r.slot + 1)) < 2 for r in out)
