"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twoview.functions import expressions as E
from twoview.operators.model import CodeModel, ModelSpec, unpack_words
from twoview.operators.search import over_chunks
from twoview.operators.vectors import doubles, lists, matrix


def recall_at(result: DataFrame, truth: DataFrame, ranks: tuple[int, ...] = (1, 10, 100)) -> DataFrame:
    """Share of queries whose one true neighbour is among the first R results: rows (r, recall); missing ones count as misses."""
    first = truth.where("rk = 1").select("qid", F.col("vec_id").alias("true_id"))
    at = first.join(result.select("qid", F.col("vec_id").alias("true_id"), F.col("rk").alias("at")), ["qid", "true_id"], "left")
    wide = at.agg(*[F.avg((F.coalesce("at", F.lit(1 << 30)) <= r).cast("double")).alias(f"r{r}") for r in ranks])
    return wide.select(F.explode(F.array(*[F.struct(F.lit(r).alias("r"), F.col(f"r{r}").alias("recall")) for r in ranks])).alias("s")).select("s.*")


def intersection_at(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Share of the k true neighbours among the k found, mean over queries."""
    t = truth.where(F.col("rk") <= k)
    hits = t.join(result.where(F.col("rk") <= k).select("qid", "vec_id"), ["qid", "vec_id"], "left_semi").groupBy("qid").agg(F.count("*").alias("hit"))
    each = t.groupBy("qid").agg(F.count("*").alias("n")).join(hits, "qid", "left")
    return each.agg(F.avg(F.coalesce("hit", F.lit(0)) / F.col("n")).alias("intersection"))


def coverage(truth: DataFrame, codes: DataFrame, prepared: DataFrame, model: CodeModel, taus: list[int]) -> DataFrame:
    """Share of queries whose true neighbour passes the bit test, by threshold."""
    n = model.spec.n_words
    first = truth.where("rk = 1").select("qid", "vec_id").join(codes, "vec_id").join(prepared.drop("lut"), "qid")
    h = first.select(E.hamming(E.word_columns("w", n), E.word_columns("q", n)).alias("h"))
    row = h.agg(*[F.avg((F.col("h") <= t).cast("double")).alias(f"t{t}") for t in taus])
    return row.select(F.explode(F.array(*[F.struct(F.lit(t).alias("tau"), F.col(f"t{t}").alias("coverage")) for t in taus])).alias("s")).select("s.*")


def tau_sweep(prepared: DataFrame, codes: DataFrame, truth: DataFrame, model: CodeModel, R: int = 1) -> DataFrame:
    """All thresholds in one scan: (tau, kept_share, recall).

    The true neighbour is found at tau if its own distance passes and fewer than R passing codes rank before it.
    """
    spec = model.spec
    w, q = E.word_columns("w", spec.n_words), E.word_columns("q", spec.n_words)
    first = truth.where("rk = 1").select("qid", F.col("vec_id").alias("true_id"))
    true = first.join(codes, codes.vec_id == first.true_id).join(prepared, "qid")
    known = prepared.join(
        true.select("qid", "true_id", E.hamming(w, q).alias("true_h"), E.adc(w, F.col("lut"), spec).alias("true_score")), "qid"
    )
    est = E.adc(w, F.col("lut"), spec)
    ahead = (est < F.col("true_score")) | ((est == F.col("true_score")) & (F.col("vec_id") < F.col("true_id")))
    each = over_chunks(known, 64 + 8 * spec.M * spec.K, lambda p: codes.crossJoin(p).select("qid", "true_h", E.hamming(w, q).alias("h"), ahead.cast("int").alias("ahead")))
    hist = each.groupBy("qid", "true_h", "h").agg(F.count("*").alias("n"), F.sum("ahead").alias("ahead"))
    grid = prepared.sparkSession.range(spec.bits + 1).select(F.col("id").cast("int").alias("tau"))
    per = hist.join(F.broadcast(grid), F.col("h") <= F.col("tau")).groupBy("qid", "tau", "true_h").agg(F.sum("n").alias("kept"), F.sum("ahead").alias("ahead"))
    total = hist.agg(F.sum("n").alias("total"))
    n_q = prepared.select(F.count("*").alias("nq"))
    hit = ((F.col("true_h") <= F.col("tau")) & (F.col("ahead") < R)).cast("int")
    some = per.groupBy("tau").agg(F.sum("kept").alias("kept"), F.sum(hit).alias("hits"))
    full = grid.join(some, "tau", "left").crossJoin(F.broadcast(total)).crossJoin(F.broadcast(n_q))
    return full.select("tau", (F.coalesce("kept", F.lit(0)) / F.col("total")).alias("kept_share"), (F.coalesce("hits", F.lit(0)) / F.col("nq")).alias("recall"))


def _moments(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Count, means, and sums of squares and products about the means."""
    p, q = a.mean(), b.mean()
    da, db = (a - p).ravel(), (b - q).ravel()
    return np.array([a.size, p, q, da @ da, db @ db, da @ db])


def _merged(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Moments of two sets together."""
    if not x[0] or not y[0]:
        return x if x[0] else y
    n, p, q = x[0] + y[0], y[1] - x[1], y[2] - x[2]
    w, u = x[0] * y[0] / n, y[0] / n
    return np.array([n, x[1] + p * u, x[2] + q * u, x[3] + y[3] + p * p * w, x[4] + y[4] + q * q * w, x[5] + y[5] + p * q * w])


def _corr(m: np.ndarray) -> float | None:
    return float(m[5] / np.sqrt(m[3] * m[4])) if m[0] and m[3] > 0 and m[4] > 0 else None


def mid_ranks(x: np.ndarray) -> np.ndarray:
    """Ranks within each row, ties at their mean."""
    out = np.empty(x.shape)
    for i, row in enumerate(x):
        order = np.argsort(row, kind="stable")
        ascending = row[order]
        starts = np.flatnonzero(np.concatenate([[True], ascending[1:] != ascending[:-1]]))
        n = np.diff(np.append(starts, len(row)))
        out[i, order] = np.repeat(starts + (n - 1) / 2, n)
    return out


def _correlated(both: DataFrame, asked: DataFrame, spec: ModelSpec, bits: dict[str, tuple[str, str]], mismatch: bool, ranks: bool) -> DataFrame:
    """Correlation of true squared distances with each estimate over all pairs of both (vec_id, x, words) and asked (qid, q, words, lut).

    bits: the prefixes of the words of base and queries by estimator. Each task takes some queries against the whole base, which
    is sent out, and returns the moments of its pairs; ranks are within a query.
    """
    spark, n = both.sparkSession, spec.n_words
    got = both.orderBy("vec_id").toArrow()
    word = lambda t, at: np.stack([t[f"{at}{i}"].to_numpy() for i in range(n)], 1).view(np.uint64)
    x, inverse = np.unique(matrix(got["x"]), axis=0, return_inverse=True)
    sent = spark.sparkContext.broadcast((x, inverse.ravel(), {k: word(got, w) for k, (w, _) in bits.items()}))
    names = ["adc", *bits, *(["index_mismatch"] if mismatch else [])]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, inverse, words = sent.value
        x2, numbers = (x * x).sum(1), unpack_words(words[next(iter(bits))], spec).T.copy()
        at = numbers + np.arange(spec.M)[:, None] * spec.K
        total = {c: np.zeros((2, 6)) for c in names}
        rows = max(1, (1 << 21) // max(len(inverse), 1))
        for batch in batches:
            table = pa.Table.from_batches([batch])
            q, lut = matrix(table["q"]), matrix(table["lut"])
            asked_words = {k: word(table, p) for k, (_, p) in bits.items()}
            own = unpack_words(asked_words[next(iter(bits))], spec) if mismatch else None
            for a in range(0, len(q) if len(inverse) else 0, rows):
                block = q[a : a + rows]
                d2 = ((block * block).sum(1)[:, None] + x2 - 2 * block @ x.T)[:, inverse]
                est = {"adc": sum(lut[a : a + rows, at[m]] for m in range(spec.M))}
                for k in bits:
                    est[k] = sum(np.bitwise_count(asked_words[k][a : a + rows, w, None] ^ words[k][None, :, w]).astype(float) for w in range(n))
                if mismatch:
                    est["index_mismatch"] = sum((own[a : a + rows, m, None] != numbers[m]).astype(float) for m in range(spec.M))
                true = mid_ranks(d2) if ranks else None
                for c in names:
                    total[c][0] = _merged(total[c][0], _moments(d2, est[c]))
                    if ranks:
                        total[c][1] = _merged(total[c][1], _moments(true, mid_ranks(est[c])))
        yield pa.RecordBatch.from_arrays([pa.array(names), lists(np.stack([total[c].ravel() for c in names]))], names=["estimator", "m"])

    columns = ["q", "lut", *dict.fromkeys(f"{p}{i}" for _, p in bits.values() for i in range(n))]
    spread = asked.select(*columns).repartition(max(2 * spark.sparkContext.defaultParallelism, 8))
    sums = {c: np.zeros((2, 6)) for c in names}
    for r in spread.mapInArrow(run, "estimator string, m array<double>").collect():  # a few numbers a task
        for i, m in enumerate(np.array(r.m).reshape(2, 6)):
            sums[r.estimator][i] = _merged(sums[r.estimator][i], m)
    rows = [(c, _corr(sums[c][0]), *([_corr(sums[c][1])] if ranks else [])) for c in names]
    return spark.createDataFrame(rows, "estimator string, pearson double" + ", spearman double" * ranks)


def correlations(prepared: DataFrame, queries: DataFrame, codes: DataFrame, base: DataFrame, model: CodeModel, ranks: bool = True) -> DataFrame:
    """Correlation of true squared distances with each estimate over all pairs: (estimator, pearson, and with ranks spearman).

    The base is sent to the tasks, so it is one that fits in memory.
    """
    from twoview.operators.search import as_queries

    asked = prepared.join(as_queries(queries), "qid")
    both = codes.join(base.select("vec_id", doubles().alias("x")), "vec_id")
    return _correlated(both, asked, model.spec, {"hamming": ("w", "q")}, True, ranks)


def one_bit_edges(codebook: DataFrame, numbering: DataFrame) -> DataFrame:
    """Mean centroid distance over pairs whose numbers differ in one bit, and over all pairs, by slice."""
    n = codebook.join(numbering, ["m", "i"]).select("m", "code", "centroid")
    a, b = n.select("m", F.col("code").alias("ca"), F.col("centroid").alias("a")), n.select("m", F.col("code").alias("cb"), F.col("centroid").alias("b"))
    pairs = a.join(b, "m").where("ca <> cb").withColumn("d", F.sqrt(E.l2sq(F.col("a"), F.col("b"))))
    near = F.bit_count(F.col("ca").bitwiseXOR(F.col("cb"))) == 1
    return pairs.groupBy("m").agg(F.avg(F.when(near, F.col("d"))).alias("one_bit"), F.avg("d").alias("all_pairs"))


def timed(make: Callable[[], DataFrame], repeats: int = 1) -> float:
    """Seconds to run a plan into nowhere, the best of some runs; a new plan each time, as finished shuffles would be reused."""
    best = float("inf")
    for _ in range(repeats):
        df, t = make(), time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        best = min(best, time.perf_counter() - t)
    return best


def op_counts(n_queries: int, n_base: int, model: CodeModel, kept_share: float) -> dict[str, float]:
    """Work of a two-stage search, free of hardware: words compared, look-ups added, and what look-ups alone would take."""
    pairs = n_queries * n_base
    return {"word_xors": float(pairs * model.spec.n_words), "lut_adds": pairs * kept_share * model.spec.M, "full_lut_adds": float(pairs * model.spec.M), "bytes": float(n_base * model.spec.code_bytes)}


def summarise_runs(runs: DataFrame, by: list[str], values: list[str]) -> DataFrame:
    """Mean and deviation over seeds."""
    return runs.groupBy(*by).agg(*[f for v in values for f in (F.avg(v).alias(f"{v}_mean"), F.stddev_samp(v).alias(f"{v}_std"))])


def _sides(queries: DataFrame, base: DataFrame, models: dict[str, CodeModel]) -> tuple[DataFrame, DataFrame]:
    """Base (vec_id, x, words by model) and queries (qid, q, words by model, the first model's lut)."""
    from twoview.operators.quantize import encode
    from twoview.operators.search import as_queries, prepare_queries

    both, asked = base.select("vec_id", doubles().alias("x")), as_queries(queries)
    for i, (name, model) in enumerate(models.items()):
        n = model.spec.n_words
        c, p = encode(base, model), prepare_queries(queries, model)
        both = both.join(c.select("vec_id", *[F.col(f"w{k}").alias(f"{name}_w{k}") for k in range(n)]), "vec_id")
        asked = asked.join(p.select("qid", *[F.col(f"q{k}").alias(f"{name}_q{k}") for k in range(n)], *(["lut"] if i == 0 else [])), "qid")
    return both, asked


def estimate_pairs(queries: DataFrame, base: DataFrame, models: dict[str, CodeModel]) -> DataFrame:
    """All pairs (qid, vec_id, d2, adc, and bits by the name of each model), for studies on sets of a bounded size.

    The models share a quantizer and differ in its numbering, so that the first one's look-ups stand for all.
    """
    both, asked = _sides(queries, base, models)
    first, spec = next(iter(models)), next(iter(models.values())).spec
    bits = [E.hamming(E.word_columns(f"{m}_w", spec.n_words), E.word_columns(f"{m}_q", spec.n_words)).cast("double").alias(m) for m in models]
    adc = E.adc(E.word_columns(f"{first}_w", spec.n_words), F.col("lut"), spec).alias("adc")
    size = 8 * (4096 + spec.M * spec.K)
    return over_chunks(asked, size, lambda p: both.crossJoin(p).select("qid", "vec_id", E.l2sq(F.col("x"), F.col("q")).alias("d2"), adc, *bits))


def triplet(queries: DataFrame, base: DataFrame, before: CodeModel, after: CodeModel) -> DataFrame:
    """Correlation of true distances with look-ups and with bits before and after: (estimator, pearson, spearman).

    Spearman's ranks are within each query, ties at their mean. The base is sent to the tasks, so it is one that fits in memory.
    """
    models = {"hamming_before": before, "hamming_after": after}
    return _correlated(*_sides(queries, base, models), before.spec, {m: (f"{m}_w", f"{m}_q") for m in models}, False, True)


def decile_means(queries: DataFrame, base: DataFrame, model: CodeModel) -> DataFrame:
    """Mean true distance, look-up estimate and bits by decile of each query's true distances; base is a sample."""
    pairs = estimate_pairs(queries, base, {"hamming": model})
    tiles = pairs.withColumn("decile", F.ntile(10).over(Window.partitionBy("qid").orderBy("d2", "vec_id")))
    return tiles.groupBy("decile").agg(F.avg("d2").alias("true_d2"), F.avg("adc").alias("adc"), F.avg("hamming").alias("hamming"), F.count("*").alias("pairs"))
