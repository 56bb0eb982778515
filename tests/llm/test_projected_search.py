import numpy as np
from pyspark.sql import functions as F

from twoview.llm.projected_search import chi_square_cdf, projected_search


def brute(rows, k):
    ok = [(i, np.array(v, float)) for i, v in rows if i is not None and v is not None and None not in v and len(v) == 6 and np.isfinite(v).all() and np.any(v)]
    out = {}
    for i, q in ok:
        if i % 20 == 0:
            out[i] = [j for _, j in sorted((-round(float((x * q).sum()), 12), j) for j, x in ok if j != i)[:k]]
    return out


def test_matches_brute_force_when_sure(spark):
    rng = np.random.default_rng(4)
    rows = [(i, (rng.normal(size=6) * rng.uniform(0.5, 3)).tolist()) for i in range(700)]
    rows += [(1000 + i, rows[40][1]) for i in range(90)]
    rows += [(2000, None), (2020, [0.0] * 6), (2040, [1.0] * 5 + [float("nan")]), (2060, [1.0, None, 1.0, 1.0, 1.0, 1.0]), (2080, [1.0] * 3), (None, [1.0] * 6)]
    df = spark.createDataFrame([(i, v, 0) for i, v in rows], "vec_id long, embedding array<double>, x int").repartition(4)
    for args in ({}, {"cell_rows": 64, "leaf": 16, "query_rows": 10}):
        got = {}
        for r in projected_search(df, F.col("vec_id") % 20 == 0, k=7, sure=1.0, **args).orderBy("query_id", "rank").collect():
            got.setdefault(r.query_id, []).append(r.vec_id)
        assert got == brute(rows, 7)


def test_recall_with_stopping(spark):
    rng = np.random.default_rng(5)
    centers = rng.normal(size=(40, 6)) * 4
    rows = [(i, (centers[i % 40] + rng.normal(size=6) * 0.3).tolist()) for i in range(2000)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    want = brute(rows, 10)
    got = projected_search(df, F.col("vec_id") % 20 == 0, k=10, cell_rows=128, leaf=16).collect()
    assert len(got) == sum(map(len, want.values()))
    assert np.mean([r.vec_id in want[r.query_id] for r in got]) >= 0.9


def test_few_and_none(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.5, 0.5])], "vec_id long, embedding array<float>")
    assert [tuple(r) for r in projected_search(df, F.col("vec_id") % 20 == 0).collect()] == [(0, 1, 1, 0.5)]
    assert projected_search(df.limit(0), F.lit(True)).count() == 0


def test_chi_square():
    assert np.allclose(chi_square_cdf(np.array([0.0, 2.0, 7.3441, 15.5073]), 8), [0, 0.018988, 0.5, 0.95], atol=1e-4)
