"""Registered queries of trained quantizers, numberings, rotations and coarse cells, each with an oracle.

The Spark side trains on the given tables. The SQL takes the constants that the same seeded trainers learn
from the oracle's tables as VALUES (see learned) and computes all the rest anew.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twoview.functions import expressions as E
from twoview.functions import udfs as U
from twoview.operators import assignment as A
from twoview.operators import binary as B
from twoview.operators import calibrate as C
from twoview.operators import coarse as I
from twoview.operators import graph as G
from twoview.operators import linear as L
from twoview.operators import measure as R
from twoview.operators import quantize as Q
from twoview.operators import search as S
from twoview.operators import vectors as V
from twoview.operators.model import CodeModel
from twoview.plans import learned as N
from twoview.plans import sqlkit as K
from twoview.plans.registry import query
from twoview.plans.vector_queries import _PAIRS, COMMON, TAU, TINY, _bits_knn, _coarse, _first, _ready, _round, _split
from twoview.sources import vectors as src


def _model(spark: SparkSession, d: str, construction: str = "dist_assigned") -> tuple[V.Split, CodeModel]:
    s = _split(spark, d)
    model = Q.train_pq(s.train, 16, 4, dims=64, seed=42)
    return s, model if construction == "plain" else A.fit_assignment(spark, model, construction, n_iter=N.COOL, seed=42)[0]


def _learned(spark: SparkSession, d: str, construction: str = "dist_assigned") -> tuple[V.Split, CodeModel, DataFrame, DataFrame]:
    s, model = _model(spark, d, construction)
    return s, model, S.prepare_queries(s.query, model), Q.encode(s.base, model)


def _sql_model(d: str, construction: str = "dist_assigned") -> CodeModel:
    model = N.plain(d)
    return model if construction == "plain" else model.relabelled(N.numbering(d, "anneal"), construction)


def _base(d: str, construction: str = "dist_assigned") -> tuple[str, ...]:
    """Vectors, splits, the trained book in the order of its numbers, codes and words."""
    return K.vectors(), K.splits(), N.book(_sql_model(d, construction)), K.nearest(64, 16), K.words(4)


_H = K.ham("a.w", "b.w")
_KEPT = f"kept AS (SELECT adc.* FROM adc JOIN wrd a ON a.vec_id = qid JOIN wrd b ON b.vec_id = adc.vec_id WHERE {_H} <= {{tau}})"
_TAU = f"(SELECT max(h) FROM (SELECT h, sum(n) OVER (ORDER BY h) / sum(n) OVER () AS s FROM (SELECT {_H} AS h, count(*) AS n FROM wrd a, wrd b WHERE a.vec_id % 10 BETWEEN 1 AND 3 AND b.vec_id % 10 >= 4 GROUP BY 1)) WHERE s <= 0.05)"
_TRUE = f"true1 AS (SELECT qid, vec_id FROM (SELECT qid, vec_id, {K.sqd('e', 'q', 64)} AS s FROM base, qry) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) = 1)"


# quantizer and numbering


@query("train_pq", lambda d: K.with_(K.vectors(), K.splits(), N.book(N.plain(d)), K.nearest(64, 16, "trn", "n"), K.lloyd(64, 16, "cb", "n", "b")) + "SELECT m::INTEGER AS m, i::INTEGER AS i, k::INTEGER AS k, round(c[k + 1], 6) AS x FROM b, range(4) r(k)")
def train_pq(spark: SparkSession, d: str) -> DataFrame:
    """The trained codebook; the SQL makes one more round of k-means from it, which must leave it as it is."""
    book = Q.codebook_frame(spark, Q.train_pq(_split(spark, d).train, 16, 4, dims=64, seed=42))
    return book.select("m", "i", F.posexplode("centroid").alias("k", "x")).select("m", "i", F.col("k").cast("int").alias("k"), F.round("x", 6).alias("x"))


@query("train_pq_grouped", lambda d: K.with_(N.book(N.plain(d))) + "SELECT m, i, round(list_sum(c), 6) AS total FROM cb")
def train_pq_grouped(spark: SparkSession, d: str) -> DataFrame:
    """One task a slice learns what the driver learns."""
    book = Q.codebook_frame(spark, Q.train_pq(_split(spark, d).train, 16, 4, dims=64, seed=42, engine="grouped"))
    return book.select("m", "i", F.round(F.aggregate("centroid", F.lit(0.0), lambda a, v: a + v), 6).alias("total"))


def _losses(d: str, how: str) -> str:
    pairs = "dist AS" + _PAIRS.split("dist AS", 1)[1].rstrip()
    return (
        K.with_(N.book(N.plain(d)), N.permutation(N.numbering(d, how)), pairs)
        + "SELECT sc.m, round(sum(pow(0.5, f) * (bit_count(xor(sc.i, sc.j))::BIGINT - f) ** 2), 6) AS first_loss, round(sum(pow(0.5, f) * (bit_count(xor(p.code, q.code))::BIGINT - f) ** 2), 6) AS best_loss "
        "FROM sc JOIN pi p ON p.m = sc.m AND p.i = sc.i JOIN pi q ON q.m = sc.m AND q.i = sc.j GROUP BY sc.m"
    )


def _summary(spark: SparkSession, trace) -> DataFrame:
    t = spark.createDataFrame(trace)
    ends = t.groupBy("m").agg(F.min_by("loss", "iter").alias("first_loss"), F.max_by("loss", "iter").alias("best_loss"))
    return ends.select(F.col("m").cast("int").alias("m"), *[F.round(c, 6).alias(c) for c in ("first_loss", "best_loss")])


@query("anneal_summary", lambda d: _losses(d, "anneal"))
def anneal_summary(spark: SparkSession, d: str) -> DataFrame:
    """Loss of each slice before and after annealing to the end of its cooling."""
    model = Q.train_pq(_split(spark, d).train, 16, 4, dims=64, seed=42)
    return _summary(spark, A.fit_assignment(spark, model, "dist_assigned", n_iter=N.COOL, seed=42)[1])


@query("greedy_summary", lambda d: _losses(d, "greedy"))
def greedy_summary(spark: SparkSession, d: str) -> DataFrame:
    """Loss of each slice before and after greedy switching."""
    model = Q.train_pq(_split(spark, d).train, 16, 4, dims=64, seed=42)
    return _summary(spark, A.fit_assignment(spark, model, "dist_assigned", optimizer="greedy", seed=42)[1])


@query("learned_numbering", lambda d: K.with_(N.permutation(N.numbering(d, "anneal"))) + "SELECT m, count(DISTINCT code) AS codes, bit_xor(code * 31 + i) AS digest FROM pi GROUP BY m")
def learned_numbering(spark: SparkSession, d: str) -> DataFrame:
    """Each slice's numbering: a bijection, the same wherever it is learned."""
    _, plain = _model(spark, d, "plain")
    model = A.fit_assignment(spark, plain, "dist_assigned", n_iter=N.COOL, seed=42)[0]
    rows = [(m, i, int(np.flatnonzero((model.codebook[m] == plain.codebook[m][i]).all(1))[0])) for m in range(16) for i in range(16)]
    return spark.createDataFrame(rows, "m int, i int, code bigint").groupBy("m").agg(F.countDistinct("code").alias("codes"), F.bit_xor(F.col("code") * 31 + F.col("i")).alias("digest"))


def _swap_sql() -> str:
    def num(v: str) -> str:
        return f"(CASE {v} WHEN 3 THEN 9 WHEN 9 THEN 3 ELSE {v} END)"

    def dis(name: str, n) -> str:
        near = f"bit_count(xor({n('b.i')}, {n('b.j')})) < bit_count(xor({n('a.i')}, {n('a.j')}))"
        return f"{name} AS (SELECT a.m, a.i, a.j, count(*) FILTER (WHERE b.d > a.d AND {near}) AS r, greatest(count(*) FILTER (WHERE b.d < a.d), 1) AS rank FROM dist a JOIN dist b ON a.m = b.m AND a.i = b.i GROUP BY a.m, a.i, a.j, a.d)"

    harm = "hm AS (SELECT n, coalesce(list_sum([1.0 / z for z in range(1, n + 1)]), 0)::DOUBLE AS l FROM range(17) t(n))"
    total = "{n} AS (SELECT m, sum(l / rank) FILTER (WHERE i <> j) AS v FROM {s} JOIN hm ON hm.n = {s}.r GROUP BY m)"
    parts = [_PAIRS.rstrip(), dis("d0", str), dis("d1", num), harm, total.format(n="t0", s="d0"), total.format(n="t1", s="d1")]
    return ", ".join(parts) + " SELECT m::INTEGER AS m, round(t1.v - t0.v, 6) AS delta, round(t1.v - t0.v, 6) AS whole FROM t0 JOIN t1 USING (m)"


@query("swap_delta_rank", _swap_sql())
def swap_delta_rank(spark: SparkSession, d: str) -> DataFrame:
    """The incremental update of the ranking loss, and the whole difference beside it."""
    _, model = _first(spark, d)
    rows, swapped = [], np.arange(16)
    swapped[[3, 9]] = 9, 3
    for m in range(16):
        loss, pi = A.RankLoss(model.codebook[m], 4), np.arange(16)
        loss.start(pi)
        rows.append((m, float(loss.delta(pi, 3, 9)), float(loss.full(swapped) - loss.full(pi))))
    return spark.createDataFrame(rows, "m int, delta double, whole double").select("m", F.round("delta", 6).alias("delta"), F.round("whole", 6).alias("whole"))


# searches on the trained, annealed code


@query("learned_adc_knn", lambda d: K.with_(*_base(d), K.adc_pairs(64, 16)) + K.top("adc", 10))
def learned_adc_knn(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _learned(spark, d)
    return _round(S.adc_knn(p, c, model, 10))


@query("learned_hamming_knn", lambda d: K.with_(*_base(d), f"p AS (SELECT a.vec_id AS qid, b.vec_id, {_H}::DOUBLE AS score FROM wrd a, wrd b WHERE a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4)") + K.top("p", 10))
def learned_hamming_knn(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _learned(spark, d)
    return _round(S.hamming_knn(p, c, model, 10))


@query("learned_two_stage", lambda d: K.with_(*_base(d), K.adc_pairs(64, 16), _KEPT.format(tau=_TAU)) + K.top("kept", 10))
def learned_two_stage(spark: SparkSession, d: str) -> DataFrame:
    """The method itself: trained quantizer, annealed numbering, threshold from training pairs, two stages."""
    s, model, p, c = _learned(spark, d)
    return _round(S.two_stage_knn(p, c, model, 10, C.calibrate_tau(S.prepare_queries(s.train, model), c, model, 0.05)))


@query("learned_two_stage_plain", lambda d: K.with_(*_base(d, "plain"), K.adc_pairs(64, 16), _KEPT.format(tau=_TAU)) + K.top("kept", 10))
def learned_two_stage_plain(spark: SparkSession, d: str) -> DataFrame:
    """The same on the numbers as k-means left them, at the same share of kept pairs."""
    s, model, p, c = _learned(spark, d, "plain")
    return _round(S.two_stage_knn(p, c, model, 10, C.calibrate_tau(S.prepare_queries(s.train, model), c, model, 0.05)))


@query("learned_mismatch_knn", lambda d: K.with_(*_base(d), "mm AS (SELECT q.vec_id AS qid, b.vec_id, count(*) FILTER (WHERE q.i <> b.i) AS h FROM enc q JOIN enc b USING (m) WHERE q.vec_id % 10 = 0 AND b.vec_id % 10 >= 4 GROUP BY 1, 2)") + K.top("mm", 10, "h::DOUBLE"))
def learned_mismatch_knn(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _learned(spark, d)
    return _round(S.mismatch_knn(p, c, model, 10))


def _recall(construction: str, d: str) -> str:
    rank = "{n} AS (SELECT qid, vec_id, row_number() OVER (PARTITION BY qid ORDER BY score, vec_id) AS rk FROM {s})"
    parts = [*_base(d, construction), K.adc_pairs(64, 16), _KEPT.format(tau=_TAU), _TRUE, f"hm AS (SELECT a.vec_id AS qid, b.vec_id, {_H} AS score FROM wrd a, wrd b WHERE a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4)"]
    parts += [rank.format(n=n, s=s) for n, s in (("r1", "adc"), ("r2", "kept"), ("r3", "hm"))]
    one = "SELECT '{e}' AS estimator, r::INTEGER AS r, round(avg(coalesce(rk <= r, false)::INTEGER), 6) AS recall FROM true1 LEFT JOIN {n} USING (qid, vec_id), (VALUES (1), (10), (100)) t(r) GROUP BY r"
    return K.with_(*parts) + " UNION ALL ".join(one.format(e=e, n=n) for e, n in (("adc", "r1"), ("two_stage", "r2"), ("hamming", "r3")))


def _recalls(spark: SparkSession, d: str, construction: str) -> DataFrame:
    s, model, p, c = _learned(spark, d, construction)
    tau = C.calibrate_tau(S.prepare_queries(s.train, model), c, model, 0.05)
    truth = S.exact_knn(s.query, s.base, 1)
    got = [("adc", S.adc_knn(p, c, model, 100)), ("two_stage", S.two_stage_knn(p, c, model, 100, tau)), ("hamming", S.hamming_knn(p, c, model, 100))]
    tables = [R.recall_at(x, truth).select(F.lit(e).alias("estimator"), "r", F.round("recall", 6).alias("recall")) for e, x in got]
    return tables[0].unionAll(tables[1]).unionAll(tables[2])


for _c in ("plain", "dist_assigned"):

    @query(f"recall_{_c}", lambda d, c=_c: _recall(c, d))
    def recall_construction(spark: SparkSession, d: str, c: str = _c) -> DataFrame:
        """Recall of three estimators on a construction, at 5 % of training pairs kept."""
        return _recalls(spark, d, c)


@query("two_stage_at_least", K.with_(*COMMON, K.nearest(64, 16), K.words(4, "gray"), K.adc_pairs(64, 16), f"pr AS (SELECT adc.*, {_H} AS h FROM adc JOIN wrd a ON a.vec_id = qid JOIN wrd b ON b.vec_id = adc.vec_id)", "own AS (SELECT qid, greatest(16, min(h)) AS tau FROM (SELECT qid, h, sum(count(*)) OVER (PARTITION BY qid ORDER BY h) AS c FROM pr GROUP BY qid, h) WHERE c >= 20 GROUP BY qid)", "kept AS (SELECT pr.* FROM pr JOIN own USING (qid) WHERE h <= tau)") + K.top("kept", 10))
def two_stage_at_least(spark: SparkSession, d: str) -> DataFrame:
    """Thresholds that widen by query until twenty pairs survive."""
    _, model, p, c = _ready(spark, d, "gray")
    return _round(S.two_stage_at_least(p, c, model, 10, 16, 20))


@query("search_one", K.with_(*COMMON, K.nearest(64, 16), K.words(4, "gray"), K.adc_pairs(64, 16), _KEPT.format(tau=TAU)) + "SELECT vec_id, round(score, 6) AS score FROM kept WHERE qid = (SELECT min(qid) FROM qry) ORDER BY kept.score, vec_id LIMIT 10")
def search_one(spark: SparkSession, d: str) -> DataFrame:
    """One query as literals in the scan's filter."""
    s, model, _, c = _ready(spark, d, "gray")
    return S.search_one(V.lowest_ids(s.query, 1)[1][0], c, model, 10, TAU).select("vec_id", F.round("score", 6).alias("score"))


# binary codes


def _bits_sql(r: str, n: int) -> str:
    bits = f"{r}, s AS (SELECT vec_id, list(list_sum([e[z]*c[z] for z in range(1, 65)]) >= shift ORDER BY j) AS b FROM v, r GROUP BY vec_id)"
    return f"{bits}, fh AS (SELECT a.vec_id AS qid, b.vec_id, list_sum([(a.b[z] <> b.b[z])::INTEGER for z in range(1, {n + 1})])::DOUBLE AS score FROM s a, s b WHERE a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4)"


@query("lsh_projection_knn", lambda d: K.with_(K.vectors(), _bits_sql(N.directions(B.fit_sign_lsh(64, 128, 7, orthogonal=False).image), 128)) + K.top("fh", 10))
def lsh_projection_knn(spark: SparkSession, d: str) -> DataFrame:
    return _bits_knn(spark, d, B.fit_sign_lsh(64, 128, 7, orthogonal=False))


@query("itq_knn", lambda d: K.with_(K.vectors(), _bits_sql(N.directions(N.rotated_bits(d)), 64)) + K.top("fh", 10))
def itq_knn(spark: SparkSession, d: str) -> DataFrame:
    return _bits_knn(spark, d, B.fit_itq(_split(spark, d).train, 64, 64))


@query("two_stage_foreign_bits", lambda d: K.with_(*_base(d, "plain"), K.adc_pairs(64, 16), _bits_sql(N.directions(N.rotated_bits(d)), 64), "kept AS (SELECT adc.* FROM adc JOIN fh USING (qid, vec_id) WHERE fh.score <= 28)") + K.top("kept", 10))
def two_stage_foreign_bits(spark: SparkSession, d: str) -> DataFrame:
    """Bits of an unrelated code as the first stage; they take room of their own."""
    s, model, p, c = _learned(spark, d, "plain")
    bits = B.fit_itq(s.train, 64, 64)
    p, c = p.join(B.encode_bits(s.query, bits, "g", "qid"), "qid"), c.join(B.encode_bits(s.base, bits, "f"), "vec_id")
    return _round(S.two_stage_knn(p, c, model, 10, 28, by="foreign"))


@query("pca_variances", lambda d: K.with_(K.vectors(), N.directions(N.principal(N.embeddings(d)[1], 16))) + "SELECT j AS k, round(var_pop(x), 6) AS variance FROM (SELECT vec_id, j, list_sum([e[z]*c[z] for z in range(1, 65)]) AS x FROM v, r) GROUP BY j")
def pca_variances(spark: SparkSession, d: str) -> DataFrame:
    """Variance along each of 16 principal directions, largest first."""
    v = src.emb(spark, d)
    out = V.apply_map(v, L.fit_pca(v, 64, 16))
    return out.select(F.posexplode("embedding").alias("k", "x")).groupBy(F.col("k").cast("int").alias("k")).agg(F.round(F.var_pop("x"), 6).alias("variance"))


# coarse cells, over the first codebook in Gray order as in the other coarse queries


def _cells(d: str, parts: int = 2) -> str:
    """Coarse centroids, part distances of all vectors, their cells, and all cells of all vectors in order of distance."""
    model = N.coarse(N.training(d), 3, parts)
    w = 64 // parts
    total, cell, join = ("a.d + b.d", "a.u * 8 + b.u", "JOIN cd b USING (vec_id) WHERE a.part = 0 AND b.part = 1") if parts == 2 else ("a.d", "a.u", "WHERE a.part = 0")
    return ", ".join(
        [
            N.book(model, "cc(part, u, c)"),
            f"cd AS (SELECT vec_id, part, u, {K.sqd(f'e[part*{w}+1 : part*{w}+{w}]', 'c', w)} AS d FROM v, cc)",
            f"po AS (SELECT vec_id, ({cell})::BIGINT AS cell, {total} AS cell_d2, row_number() OVER (PARTITION BY vec_id ORDER BY {total}, {cell})::INTEGER AS ord FROM cd a {join})",
            "cl AS (SELECT vec_id, cell FROM po WHERE ord = 1)",
        ]
    )


def _gray(d: str, parts: int = 2) -> tuple[str, ...]:
    return *COMMON, K.nearest(64, 16), K.words(4, "gray"), _cells(d, parts)


@query("multi_index_cells", lambda d: K.with_(K.vectors(), _cells(d)) + "SELECT cell, count(*) AS n FROM cl WHERE vec_id % 10 >= 4 GROUP BY cell")
def multi_index_cells(spark: SparkSession, d: str) -> DataFrame:
    s, ix = _coarse(spark, d)
    return I.encode_cells(s.base, ix).groupBy("cell").agg(F.count("*").alias("n"))


@query("probe_cells", lambda d: K.with_(K.vectors(), _cells(d)) + "SELECT vec_id AS qid, cell, ord, round(cell_d2, 6) AS cell_d2 FROM po WHERE vec_id % 10 = 0 AND ord <= 8")
def probe_cells(spark: SparkSession, d: str) -> DataFrame:
    s, ix = _coarse(spark, d)
    return I.probe_cells(s.query, ix, 8).select("qid", "cell", "ord", F.round("cell_d2", 6).alias("cell_d2"))


def _ivf(d: str, n_probe: int, tau: int, parts: int = 2) -> str:
    found = f"kept AS (SELECT adc.* FROM adc JOIN cl ON cl.vec_id = adc.vec_id JOIN po ON po.vec_id = adc.qid AND po.cell = cl.cell AND po.ord <= {n_probe} JOIN wrd a ON a.vec_id = adc.qid JOIN wrd b ON b.vec_id = adc.vec_id WHERE {_H} <= {tau})"
    return K.with_(*_gray(d, parts), K.adc_pairs(64, 16), found) + K.top("kept", 10)


@query("ivf_search", lambda d: _ivf(d, 16, 28))
def ivf_search(spark: SparkSession, d: str) -> DataFrame:
    """A quarter of the cells, and bits under the greatest threshold."""
    s, ix = _coarse(spark, d)
    return _round(I.search_ivf(I.probe_cells(s.query, ix, 16), I.encode_cells(s.base, ix), ix, 10, 28))


@query("ivf_search_dealt", lambda d: _ivf(d, 16, 28))
def ivf_search_dealt(spark: SparkSession, d: str) -> DataFrame:
    """The same beyond a size that can be sent out: probes and codes dealt by cell and salt, tables made where they meet."""
    s, ix = _coarse(spark, d)
    return _round(I.search_ivf_dealt(s.query, I.encode_cells(s.base, ix), ix, 10, 16, 28, code_rows=7, query_rows=5))


@query("ivf_search_salted", lambda d: _ivf(d, 16, 28))
def ivf_search_salted(spark: SparkSession, d: str) -> DataFrame:
    s, ix = _coarse(spark, d)
    return _round(I.search_ivf_salted(I.probe_cells(s.query, ix, 16), I.encode_cells(s.base, ix), ix, 10, 28))


@query("single_index_search", lambda d: _ivf(d, 3, 28, 1))
def single_index_search(spark: SparkSession, d: str) -> DataFrame:
    s, ix = _coarse(spark, d, parts=1)
    return _round(I.search_ivf(I.probe_cells(s.query, ix, 3), I.encode_cells(s.base, ix), ix, 10, 28))


def _residual(d: str) -> str:
    x, model = N.training(d), N.coarse(N.training(d), 3, 2)
    index = I.CoarseIndex(model, N.plain(d))
    book = N.quantizer(x - index.center(index.cells(x)), 16, 4, 1)
    ds = "e[m*4+1 : m*4+4]"
    parts = [
        K.vectors(), K.splits(), _cells(d), N.book(book),
        "ct AS (SELECT (a.u * 8 + b.u)::BIGINT AS cell, list_concat(a.c, b.c) AS g FROM cc a, cc b WHERE a.part = 0 AND b.part = 1)",
        "rb AS (SELECT v.vec_id, [e[z] - g[z] for z in range(1, 65)] AS e FROM v JOIN cl USING (vec_id) JOIN ct USING (cell) WHERE v.vec_id % 10 >= 4)",
        K.nearest(64, 16, "rb"),
        "rq AS (SELECT v.vec_id AS qid, po.cell, [e[z] - g[z] for z in range(1, 65)] AS e FROM v JOIN po USING (vec_id) JOIN ct USING (cell) WHERE v.vec_id % 10 = 0 AND ord <= 16)",
        f"lt AS (SELECT qid, cell, m, i, {K.sqd(ds, 'c', 4)} AS d FROM rq, cb)",
        "p AS (SELECT qid, enc.vec_id, list_sum(list(d ORDER BY enc.m)) AS score FROM enc JOIN cl USING (vec_id) JOIN lt ON lt.cell = cl.cell AND lt.m = enc.m AND lt.i = enc.i GROUP BY qid, enc.vec_id)",
    ]
    return K.with_(*parts) + K.top("p", 10)


@query("residual_search", _residual)
def residual_search(spark: SparkSession, d: str) -> DataFrame:
    """Codes of what is left after the cell's center, a table for each probe."""
    s, ix = _coarse(spark, d, residual=True)
    return _round(I.search_ivf(I.probe_cells(s.query, ix, 16), I.encode_cells(s.base, ix), ix, 10))


def _tuned(d: str) -> str:
    pr = f"pr AS (SELECT adc.qid, adc.vec_id, score, ord, {_H} AS h FROM adc JOIN cl ON cl.vec_id = adc.vec_id JOIN po ON po.vec_id = adc.qid AND po.cell = cl.cell JOIN wrd a ON a.vec_id = adc.qid JOIN wrd b ON b.vec_id = adc.vec_id)"
    per = "pe AS (SELECT n_probe, tau, qid, count(*) AS c, count(*) FILTER (WHERE h <= tau) AS l, arg_min(vec_id, {'s': score, 'v': vec_id}) FILTER (WHERE h <= tau) AS best FROM pr, (VALUES (1), (4), (16), (64)) p(n_probe), (VALUES (20), (28), (64)) t(tau) WHERE ord <= n_probe GROUP BY ALL)"
    al = "al AS (SELECT n_probe, tau, sum(c)::BIGINT AS candidates, sum(l)::BIGINT AS lookups, count(*) FILTER (WHERE best = true1.vec_id) / (SELECT count(*) FROM qry) AS recall FROM pe JOIN true1 USING (qid) GROUP BY ALL)"
    return (
        K.with_(*_gray(d), K.adc_pairs(64, 16), _TRUE, pr, per, al, "co AS (SELECT *, candidates + lookups * 16 AS cost FROM al)")
        + "SELECT n_probe::INTEGER AS n_probe, tau::INTEGER AS tau, candidates, lookups, round(recall, 6) AS recall, cost::BIGINT AS cost FROM co"
    )


@query("autotune_pareto", _tuned)
def autotune_pareto(spark: SparkSession, d: str) -> DataFrame:
    s, ix = _coarse(spark, d)
    got = I.autotune(s.query, S.exact_knn(s.query, s.base, 1), I.encode_cells(s.base, ix), ix, [1, 4, 16, 64], [20, 28, 64])
    return got.select("n_probe", "tau", "candidates", "lookups", F.round("recall", 6).alias("recall"), F.col("cost").cast("bigint").alias("cost"))


# graphs


def _graph_pairs(side: str, n_probe: int, tau: int | None) -> str:
    """Codes of all against raw vectors of all, in the cells that each visits."""
    ds = "q[m*4+1 : m*4+4]"
    raw = "qs AS (SELECT vec_id AS qid, e AS q FROM v)" if side == "raw" else "qs AS (SELECT vec_id AS qid, flatten(list(c ORDER BY enc.m)) AS q FROM enc JOIN cb USING (m, i) GROUP BY vec_id)"
    test = f" JOIN wrd a ON a.vec_id = lt.qid JOIN wrd b ON b.vec_id = enc.vec_id WHERE lt.qid <> enc.vec_id AND {_H} <= {tau}" if tau is not None else " WHERE lt.qid <> enc.vec_id"
    probes = "pq AS (SELECT vec_id, cell, ord FROM po)"
    if side == "code":  # what is left of a vector also chooses its cells
        cells = f"ca AS (SELECT qid, part, u, {K.sqd('q[part*32+1 : part*32+32]', 'c', 32)} AS d FROM qs, cc)"
        probes = cells + ", pq AS (SELECT a.qid AS vec_id, (a.u * 8 + b.u)::BIGINT AS cell, row_number() OVER (PARTITION BY a.qid ORDER BY a.d + b.d, a.u * 8 + b.u) AS ord FROM ca a JOIN ca b USING (qid) WHERE a.part = 0 AND b.part = 1)"
    return ", ".join(
        [
            raw,
            probes,
            f"lt AS (SELECT qid, m, i, {K.sqd(ds, 'c', 4)} AS d FROM qs, cb)",
            f"ge AS (SELECT lt.qid AS src, enc.vec_id AS dst, list_sum(list(lt.d ORDER BY enc.m)) AS dist FROM enc JOIN cl ON cl.vec_id = enc.vec_id JOIN pq ON pq.cell = cl.cell AND pq.ord <= {n_probe} JOIN lt ON lt.qid = pq.vec_id AND lt.m = enc.m AND lt.i = enc.i{test} GROUP BY lt.qid, enc.vec_id)",
            "gr AS (SELECT src, dst, dist, row_number() OVER (PARTITION BY src ORDER BY dist, dst)::INTEGER AS rk FROM ge QUALIFY rk <= 5)",
        ]
    )


def _edges(g: DataFrame) -> DataFrame:
    return g.select("src", "dst", F.col("rk").cast("int").alias("rk"), F.round("dist", 6).alias("dist"))


@query("knn_graph", lambda d: K.with_(*_gray(d), _graph_pairs("raw", 16, 32)) + "SELECT src, dst, rk, round(dist, 6) AS dist FROM gr")
def knn_graph(spark: SparkSession, d: str) -> DataFrame:
    _, ix = _coarse(spark, d)
    return _edges(G.knn_graph(src.emb(spark, d), ix, 5, 16, 32, code_rows=64, query_rows=256))


@query("graph_descent", lambda d: K.with_(*_gray(d), _graph_pairs("raw", 4, None), "bo AS (SELECT src, dst FROM gr UNION SELECT dst, src FROM gr)", "pp AS (SELECT a.src, b.dst FROM bo a JOIN bo b ON a.dst = b.src WHERE a.src <> b.dst UNION SELECT src, dst FROM gr)", f"me AS (SELECT src, dst, {K.sqd('a.e', 'b.e', 64)} AS dist FROM pp JOIN v a ON a.vec_id = src JOIN v b ON b.vec_id = dst)") + "SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dist, dst)::INTEGER AS rk, round(dist, 6) AS dist FROM me QUALIFY rk <= 5")
def graph_descent(spark: SparkSession, d: str) -> DataFrame:
    """One round of neighbours' neighbours, measured on raw vectors."""
    _, ix = _coarse(spark, d)
    v = src.emb(spark, d)
    return _edges(G.graph_descent(G.knn_graph(v, ix, 5, 4), v, 5, hub=8))


@query("knn_graph_codes", lambda d: K.with_(*_gray(d), _graph_pairs("code", 8, 32)) + "SELECT src, dst, rk, round(dist, 6) AS dist FROM gr")
def knn_graph_codes(spark: SparkSession, d: str) -> DataFrame:
    """The graph from codes alone, as when raw vectors are gone."""
    _, ix = _coarse(spark, d)
    return _edges(G.knn_graph(src.emb(spark, d), ix, 5, 8, 32, side="code"))


def _triplet_sql(d: str) -> str:
    """Pairs with the true distance, the estimate, and bits before and after the numbering was learned; ranks with ties at their mean."""
    plain, better = N.plain(d), _sql_model(d)
    words = [K.vectors(), K.splits()]
    for name, model in (("1", plain), ("2", better)):
        words += [N.book(model, f"cb{name}(m, i, c)"), K.nearest(64, 16, "v", f"e{name}", f"cb{name}"), K.words(4, "identity", f"e{name}", f"w{name}")]
    words += ["cb AS (SELECT * FROM cb1)", "enc AS (SELECT * FROM e1)", K.adc_pairs(64, 16)]
    bits = [f"{K.ham(f'a{n}.w', f'b{n}.w')} AS h{n}" for n in "12"]
    joins = " ".join(f"JOIN w{n} a{n} ON a{n}.vec_id = adc.qid JOIN w{n} b{n} ON b{n}.vec_id = adc.vec_id" for n in "12")
    words.append(f"pr AS MATERIALIZED (SELECT adc.qid, adc.vec_id, score, {', '.join(bits)}, {K.sqd('base.e', 'qry.q', 64)} AS d2 FROM adc {joins} JOIN base ON base.vec_id = adc.vec_id JOIN qry ON qry.qid = adc.qid)")
    mid = "rank() OVER (PARTITION BY qid ORDER BY {c}) + (count(*) OVER (PARTITION BY qid, {c}) - 1) / 2.0"
    words.append("rk AS (SELECT *, " + ", ".join(f"{mid.format(c=c)} AS r_{c}" for c in ("d2", "score", "h1", "h2")) + " FROM pr)")
    row = "SELECT '{n}' AS estimator, round(corr(d2, {c}), 6) AS pearson, round(corr(r_d2, r_{c}), 6) AS spearman FROM rk"
    return K.with_(*words) + " UNION ALL ".join(row.format(n=n, c=c) for n, c in (("adc", "score"), ("hamming_before", "h1"), ("hamming_after", "h2")))


@query("correlation_triplet", _triplet_sql)
def correlation_triplet(spark: SparkSession, d: str) -> DataFrame:
    """Correlation of true distances with look-ups, and with bits before and after the numbering is learned."""
    s, plain, p, c = _learned(spark, d, "plain")
    _, better = _model(spark, d)
    return R.triplet(s.query, s.base, plain, better).select("estimator", F.round("pearson", 6).alias("pearson"), F.round("spearman", 6).alias("spearman"))


def _decile_sql(d: str) -> str:
    pr = f"pr AS MATERIALIZED (SELECT adc.qid, adc.vec_id, score, {_H} AS h, {K.sqd('base.e', 'qry.q', 64)} AS d2 FROM adc JOIN wrd a ON a.vec_id = adc.qid JOIN wrd b ON b.vec_id = adc.vec_id JOIN base ON base.vec_id = adc.vec_id JOIN qry ON qry.qid = adc.qid)"
    tile = "ti AS (SELECT *, ntile(10) OVER (PARTITION BY qid ORDER BY d2, vec_id) AS decile FROM pr)"
    return K.with_(*_base(d), K.adc_pairs(64, 16), pr, tile) + "SELECT decile::INTEGER AS decile, round(avg(d2), 6) AS true_d2, round(avg(score), 6) AS adc, round(avg(h), 6) AS hamming, count(*) AS pairs FROM ti GROUP BY decile"


@query("distance_deciles", _decile_sql)
def distance_deciles(spark: SparkSession, d: str) -> DataFrame:
    """Mean estimates by decile of each query's true distances."""
    s, model, p, c = _learned(spark, d)
    got = R.decile_means(s.query, s.base, model)
    return got.select("decile", *[F.round(x, 6).alias(x) for x in ("true_d2", "adc", "hamming")], "pairs")


def _sweep_sql(d: str) -> str:
    pr = f"pr AS MATERIALIZED (SELECT adc.qid, adc.vec_id, score, {_H} AS h FROM adc JOIN wrd a ON a.vec_id = qid JOIN wrd b ON b.vec_id = adc.vec_id)"
    return (
        K.with_(*_base(d), K.adc_pairs(64, 16), _TRUE, pr, "tt AS (SELECT pr.* FROM pr JOIN true1 USING (qid, vec_id))")
        + "SELECT tau::INTEGER AS tau, round(k / (SELECT count(*) FROM pr), 6) AS kept_share, round(hit / (SELECT count(*) FROM qry), 6) AS recall FROM (SELECT tau, (SELECT count(*) FROM pr WHERE h <= tau) AS k, "
        "(SELECT count(*) FROM tt WHERE h <= tau AND NOT EXISTS (SELECT 1 FROM pr WHERE pr.qid = tt.qid AND pr.h <= tau AND (pr.score < tt.score OR (pr.score = tt.score AND pr.vec_id < tt.vec_id)))) AS hit FROM range(65) r(tau))"
    )


@query("learned_tau_sweep", _sweep_sql)
def learned_tau_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Kept share and recall by threshold on the learned numbering."""
    s, model, p, c = _learned(spark, d)
    return R.tau_sweep(p, c, S.exact_knn(s.query, s.base, 1), model).select("tau", F.round("kept_share", 6).alias("kept_share"), F.round("recall", 6).alias("recall"))


# functions for SQL


@query("probe_cells_udtf", lambda d: K.with_(K.vectors(), _cells(d)) + "SELECT vec_id AS qid, cell, ord, round(cell_d2, 6) AS cell_d2 FROM po WHERE vec_id % 10 = 0 AND ord <= 8")
def probe_cells_udtf(spark: SparkSession, d: str) -> DataFrame:
    """The table function beside each query's row."""
    s, ix = _coarse(spark, d)
    U.register(spark)
    sent = spark.sparkContext.broadcast(ix.model)
    tables = V.map_vectors(s.query, lambda x: {"d": sent.value.tables(x)}, "d array<double>")
    tables.select(F.col("vec_id").alias("qid"), F.slice("d", 1, 8).alias("d_u"), F.slice("d", 9, 8).alias("d_v")).createOrReplaceTempView("part_distances")
    return spark.sql("SELECT qid, p.cell, p.ord, round(p.cell_d2, 6) AS cell_d2 FROM part_distances, LATERAL probe_cells(d_u, d_v, 8) p")


@query("topk_aggregate", lambda d: K.with_(*_base(d), K.adc_pairs(64, 16)) + "SELECT qid, vec_id, row_number() OVER (PARTITION BY qid ORDER BY score, vec_id)::INTEGER AS rk FROM adc QUALIFY rk <= 5")
def topk_aggregate(spark: SparkSession, d: str) -> DataFrame:
    """The five nearest by a grouped aggregate."""
    _, model, p, c = _learned(spark, d)
    scored = S.adc_knn(p, c, model, 50).select("qid", "vec_id", "score")
    lists = scored.groupBy("qid").agg(U.topk_agg(5)(F.col("vec_id"), F.col("score")).alias("ids"))
    return lists.select("qid", F.posexplode("ids").alias("rk", "vec_id")).select("qid", "vec_id", (F.col("rk") + 1).cast("int").alias("rk"))


@query("encode_function", lambda d: K.with_(*_base(d)) + "SELECT vec_id, w AS w0 FROM wrd")
def encode_function(spark: SparkSession, d: str) -> DataFrame:
    """Codes by a scalar function of the vector."""
    _, model = _model(spark, d)
    return src.emb(spark, d).select("vec_id", U.encode_udf(spark, model)(F.col("embedding"))[0].alias("w0"))


@query("case_guard", lambda d: K.with_(*_base(d), K.adc_pairs(64, 16), _KEPT.format(tau=TAU)) + "SELECT qid, count(*) AS kept, round(min(score), 6) AS nearest FROM kept GROUP BY qid")
def case_guard(spark: SparkSession, d: str) -> DataFrame:
    """Look-ups guarded by the bit test within one expression, so that rejected pairs cost none."""
    _, model, p, c = _learned(spark, d)
    w, q = E.word_columns("w", 1), E.word_columns("q", 1)
    guarded = F.when(E.hamming(w, q) <= TAU, E.adc(w, F.col("lut"), model.spec))
    pairs = S.over_chunks(p, 8 * 300, lambda x: c.crossJoin(x).select("qid", guarded.alias("score")))
    return pairs.groupBy("qid").agg(F.count("score").alias("kept"), F.round(F.min("score"), 6).alias("nearest")).where("kept > 0")


@query("agg_bitwise", lambda d: K.with_(*_base(d)) + "SELECT (vec_id % 7)::INTEGER AS part, bit_and(w) AS every, bit_or(w) AS some, bit_xor(w) AS parity, count(*) AS n FROM wrd GROUP BY 1")
def agg_bitwise(spark: SparkSession, d: str) -> DataFrame:
    """Bits that all, some and an odd number of a group's codes have."""
    s, model = _model(spark, d)
    codes = Q.encode(src.emb(spark, d), model)
    return codes.groupBy((F.col("vec_id") % 7).cast("int").alias("part")).agg(F.bit_and("w0").alias("every"), F.bit_or("w0").alias("some"), F.bit_xor("w0").alias("parity"), F.count("*").alias("n"))


@query("stratified_sample", "SELECT label, least(count(*), 1000000) AS n FROM embeddings GROUP BY label")
def stratified_sample(spark: SparkSession, d: str) -> DataFrame:
    """At most a million of each label: all there are, in tables as small as these."""
    v = src.read_table(spark, d, "embeddings")
    return V.stratified_sample(v, "label", 1_000_000).groupBy("label").agg(F.count("*").alias("n"))
