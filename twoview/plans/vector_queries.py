"""Registered queries of the vector methods.

Most have an oracle that computes everything from the raw tables: the codebook is then the slices of the first
training rows, numbered as they are, in Gray order or by an affine rule. Trained models give sums and orderings.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twoview.functions import expressions as E
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
from twoview.operators.model import CodeModel, ModelSpec
from twoview.plans import experiments as X
from twoview.plans import sqlkit as K
from twoview.plans.learned import COOL
from twoview.plans.registry import query
from twoview.sources import vectors as src

TINY = ModelSpec(64, 16, 4)
COMMON = (K.vectors(), K.splits(), K.first_codebook(64, 16, 4))
TAU = 24


def _split(spark: SparkSession, d: str) -> V.Split:
    return V.split(src.emb(spark, d))


def _first(spark: SparkSession, d: str, numbering: str = "identity") -> tuple[V.Split, CodeModel]:
    s = _split(spark, d)
    model = Q.model_of_frame(Q.codebook_first(s.train, TINY), TINY)
    if numbering != "identity":
        pi = {"gray": A.gray, "affine": A.affine}[numbering](TINY.K)
        model = model.relabelled(np.tile(pi, (TINY.M, 1)), numbering)
    return s, model


def _ready(spark: SparkSession, d: str, numbering: str = "identity") -> tuple[V.Split, CodeModel, DataFrame, DataFrame]:
    s, model = _first(spark, d, numbering)
    return s, model, S.prepare_queries(s.query, model), Q.encode(s.base, model)


def _round(df: DataFrame) -> DataFrame:
    return df.select("qid", "vec_id", F.round("score", 6).alias("score"), F.col("rk").cast("int").alias("rk"))


def _components(v: DataFrame) -> DataFrame:
    """All components of all vectors, one row each."""
    return v.select("vec_id", F.posexplode("embedding").alias("k", "x")).select("vec_id", F.col("k").cast("int").alias("k"), (F.round("x", 6) + 0.0).alias("x"))


# preparation


@query("split_counts", K.with_(K.vectors()) + "SELECT CASE WHEN vec_id % 10 = 0 THEN 'query' WHEN vec_id % 10 <= 3 THEN 'train' ELSE 'base' END AS part, count(*) AS n FROM v GROUP BY 1")
def split_counts(spark: SparkSession, d: str) -> DataFrame:
    s = _split(spark, d)
    parts = [df.select(F.lit(name).alias("part")) for name, df in (("train", s.train), ("base", s.base), ("query", s.query))]
    return parts[0].unionAll(parts[1]).unionAll(parts[2]).groupBy("part").agg(F.count("*").alias("n"))


@query("l2_norms", K.with_(K.vectors()) + "SELECT vec_id, round(list_sum([x*x for x in e]), 6) AS norm2 FROM v")
def l2_norms(spark: SparkSession, d: str) -> DataFrame:
    unit = V.l2_normalize(src.emb(spark, d))
    return unit.select("vec_id", F.round(E.dot(F.col("embedding"), F.col("embedding")), 6).alias("norm2"))


_LETTER = "[(length(lower(t)) - length(replace(lower(t), c, ''))) / greatest(length(t), 1) for c in ['" + "','".join(src.LETTERS) + "']]"


@query("letter_vectors", f"SELECT doc_id AS vec_id, k::INTEGER AS k, round(l[k + 1], 6) AS x FROM range(24) r(k), (SELECT doc_id, {_LETTER} AS l FROM (SELECT doc_id, text AS t FROM documents))")
def letter_vectors(spark: SparkSession, d: str) -> DataFrame:
    return _components(src.letters(spark, d))


@query("conv_vectors", f"SELECT conv_id AS vec_id, k::INTEGER AS k, round({_LETTER}[k + 1], 6) AS x FROM range(24) r(k), (SELECT conv_id, string_agg(text, ' ' ORDER BY turn, text) AS t FROM conversations GROUP BY conv_id)")
def conv_vectors(spark: SparkSession, d: str) -> DataFrame:
    return _components(src.convs(spark, d))


@query("page_vectors", f"SELECT page_id AS vec_id, k::INTEGER AS k, round({_LETTER}[k + 1], 6) AS x FROM range(24) r(k), (SELECT page_id, regexp_replace(html, '<[^>]*>', '', 'g') AS t FROM pages)")
def page_vectors(spark: SparkSession, d: str) -> DataFrame:
    return _components(src.web(spark, d))


@query(
    "word_vectors",
    """WITH w AS (SELECT doc_id AS vec_id, md5(unnest(string_split(lower(text), ' '))) AS h FROM documents),
    p AS (SELECT vec_id, ('0x' || substr(h, 1, 4))::BIGINT % 64 AS d, sum(CASE WHEN substr(h, 5, 1) >= '8' THEN -1.0 ELSE 1.0 END)::DOUBLE AS v FROM w GROUP BY 1, 2),
    n AS (SELECT vec_id, sqrt(sum(v * v)) AS n FROM p GROUP BY vec_id)
    SELECT vec_id, k::INTEGER AS k, round(coalesce(v, 0) / greatest(n, 1e-9), 6) + 0.0 AS x FROM n CROSS JOIN range(64) r(k) LEFT JOIN p USING (vec_id) WHERE p.d = k
    UNION ALL SELECT vec_id, k::INTEGER, 0.0 FROM n, range(64) r(k) WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.vec_id = n.vec_id AND p.d = k)""",
)
def word_vectors(spark: SparkSession, d: str) -> DataFrame:
    return _components(src.words(spark, d))


@query(
    "user_vectors",
    """WITH k AS (SELECT DISTINCT event_type FROM events), u AS (SELECT user_id, count(*) AS n, avg(value) / 100 AS mean, coalesce(stddev_pop(value), 0) / 100 AS dev,
    count(*) FILTER (WHERE dayofweek(ts) BETWEEN 1 AND 5) / count(*) AS week FROM events GROUP BY user_id),
    s AS (SELECT user_id, event_type, count(e.event_id) / n AS x FROM u CROSS JOIN k LEFT JOIN events e USING (user_id, event_type) GROUP BY user_id, event_type, n)
    SELECT user_id AS vec_id, (row_number() OVER (PARTITION BY user_id ORDER BY event_type) - 1)::INTEGER AS k, round(x, 6) AS x FROM s
    UNION ALL SELECT user_id, ((SELECT count(*) FROM k) + z)::INTEGER, round([mean, dev, week][z + 1], 6) FROM u, range(3) t(z)""",
)
def user_vectors(spark: SparkSession, d: str) -> DataFrame:
    return src.users(spark, d).select("vec_id", F.posexplode("embedding").alias("k", "x")).select("vec_id", F.col("k").cast("int").alias("k"), F.round("x", 6).alias("x"))


@query(
    "standardize_lines",
    """WITH t AS (SELECT [l_quantity, l_tax, l_extendedprice, l_discount, year(l_shipdate), dayofyear(l_shipdate), l_partkey, l_suppkey]::DOUBLE[] AS x FROM lineitem),
    s AS (SELECT k, avg(x[k + 1]) AS m, stddev_pop(x[k + 1]) AS d FROM t, range(8) r(k) GROUP BY k)
    SELECT k::INTEGER AS k, round((x[k + 1] - m) / d, 4) + 0.0 AS z, count(*) AS n FROM t, s GROUP BY 1, 2""",
)
def standardize_lines(spark: SparkSession, d: str) -> DataFrame:
    """All eight z-scores of all lines, as the count of each value of each."""
    z = src.lines(spark, d).select(F.posexplode("embedding").alias("k", "z"))
    return z.groupBy(F.col("k").cast("int").alias("k"), (F.round("z", 4) + 0.0).alias("z")).agg(F.count("*").alias("n"))


@query("validate_vectors", "SELECT count(*) AS ok, 0::BIGINT AS rejected FROM embeddings")
def validate_vectors(spark: SparkSession, d: str) -> DataFrame:
    ok, bad = V.validate(src.read_table(spark, d, "embeddings"), 64)
    return ok.agg(F.count("*").alias("ok")).crossJoin(bad.agg(F.count("*").alias("rejected")))


@query("subvector_slices", K.with_(K.vectors()) + "SELECT vec_id, m::INTEGER AS m, round(list_sum(e[m*4+1 : m*4+4]), 6) AS total FROM v, range(16) r(m)")
def subvector_slices(spark: SparkSession, d: str) -> DataFrame:
    return V.subvectors(src.emb(spark, d), 16, 64).select("vec_id", F.col("m").cast("int").alias("m"), F.round(F.aggregate("sub", F.lit(0.0), lambda s, v: s + v), 6).alias("total"))


@query("gram_matrix", K.with_(K.vectors()) + "SELECT (i-1)::INTEGER AS i, (j-1)::INTEGER AS j, round(sum(e[i]*e[j]), 6) AS v FROM v, range(1, 65) a(i), range(1, 65) b(j) WHERE i <= j GROUP BY i, j")
def gram_matrix(spark: SparkSession, d: str) -> DataFrame:
    return L.gram_sql(src.emb(spark, d)).select(F.col("i").cast("int").alias("i"), F.col("j").cast("int").alias("j"), F.round("v", 6).alias("v"))


_ROT = L.random_rotation(64, 3)


def _rotation_sql() -> str:
    rows = ", ".join(f"({j}, [" + ", ".join(repr(float(x)) for x in _ROT.matrix[:, j]) + "])" for j in range(64))
    return K.with_(K.vectors(), f"r(j, c) AS (VALUES {rows})") + "SELECT vec_id, j::INTEGER AS j, round(list_sum([e[z]*c[z] for z in range(1, 65)]), 6) AS x FROM v, r"


@query("rotate", _rotation_sql())
def rotate(spark: SparkSession, d: str) -> DataFrame:
    out = V.apply_map(src.emb(spark, d), _ROT)
    return out.select("vec_id", F.posexplode("embedding").alias("j", "x")).select("vec_id", F.col("j").cast("int").alias("j"), F.round("x", 6).alias("x"))


# quantizer


@query("codebook_first", K.with_(*COMMON) + "SELECT m, i, round(list_sum(c), 6) AS total FROM cb")
def codebook_first(spark: SparkSession, d: str) -> DataFrame:
    total = F.round(F.aggregate("centroid", F.lit(0.0), lambda s, v: s + v), 6)
    return Q.codebook_first(_split(spark, d).train, TINY).select(F.col("m").cast("int").alias("m"), F.col("i").cast("int").alias("i"), total.alias("total"))


def _lloyd(rounds: int) -> str:
    parts, book = [*COMMON], "cb"
    for r in range(rounds):
        parts += [K.nearest(64, 16, "trn", f"n{r}", book), K.lloyd(64, 16, book, f"n{r}", f"b{r}")]
        book = f"b{r}"
    return K.with_(*parts) + f"SELECT m::INTEGER AS m, i::INTEGER AS i, round(list_sum(c), 6) AS total FROM {book}"


def _lloyd_rounds(spark: SparkSession, d: str, rounds: int) -> DataFrame:
    train = _split(spark, d).train
    book = Q.codebook_first(train, TINY)
    for _ in range(rounds):
        book = Q.lloyd_round_sql(train, book, TINY)
    return book.select(F.col("m").cast("int").alias("m"), F.col("i").cast("int").alias("i"), F.round(F.aggregate("centroid", F.lit(0.0), lambda s, v: s + v), 6).alias("total"))


@query("lloyd_one_round", _lloyd(1))
def lloyd_one_round(spark: SparkSession, d: str) -> DataFrame:
    return _lloyd_rounds(spark, d, 1)


@query("lloyd_two_rounds", _lloyd(2))
def lloyd_two_rounds(spark: SparkSession, d: str) -> DataFrame:
    return _lloyd_rounds(spark, d, 2)


@query("lloyd_distributed", _lloyd(1))
def lloyd_distributed(spark: SparkSession, d: str) -> DataFrame:
    s, model = _first(spark, d)
    book = Q.codebook_frame(spark, Q.lloyd_distributed(s.train, model, 1))
    return book.select("m", "i", F.round(F.aggregate("centroid", F.lit(0.0), lambda a, v: a + v), 6).alias("total"))


@query("pq_encode", K.with_(*COMMON, K.nearest(64, 16)) + "SELECT vec_id, m, i, round(d2, 6) AS d2 FROM enc")
def pq_encode(spark: SparkSession, d: str) -> DataFrame:
    s = _split(spark, d)
    got = Q.encode_sql(src.emb(spark, d), Q.codebook_first(s.train, TINY), TINY)
    return got.select("vec_id", F.col("m").cast("int").alias("m"), F.col("i").cast("int").alias("i"), F.round("d2", 6).alias("d2"))


@query("pq_decode_error", K.with_(*COMMON, K.nearest(64, 16)) + "SELECT m, round(avg(d2), 6) AS mse FROM enc GROUP BY m")
def pq_decode_error(spark: SparkSession, d: str) -> DataFrame:
    _, model = _first(spark, d)
    return Q.reconstruction_error(src.emb(spark, d), model).select(F.col("m").cast("int").alias("m"), F.round("mse", 6).alias("mse"))


@query("pq_decode", K.with_(*COMMON, K.nearest(64, 16)) + "SELECT vec_id, round(list_sum(list(list_sum(c) ORDER BY enc.m)), 6) AS total FROM enc JOIN cb USING (m, i) GROUP BY vec_id")
def pq_decode(spark: SparkSession, d: str) -> DataFrame:
    _, model = _first(spark, d)
    back = Q.decode(Q.encode(src.emb(spark, d), model, numbers=True).select("vec_id", "codes"), model)
    return back.select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda s, v: s + v), 6).alias("total"))


for _n in ("identity", "gray", "affine"):

    @query(f"pack_words_{_n}", K.with_(*COMMON, K.nearest(64, 16), K.words(4, _n)) + "SELECT vec_id, w AS w0 FROM wrd")
    def pack_words(spark: SparkSession, d: str, numbering: str = _n) -> DataFrame:
        _, model = _first(spark, d, numbering)
        return Q.encode(src.emb(spark, d), model)


@query("code_histogram", K.with_(*COMMON, K.nearest(64, 16)) + "SELECT m, i, count(*) AS n FROM enc GROUP BY m, i")
def code_histogram(spark: SparkSession, d: str) -> DataFrame:
    _, model = _first(spark, d)
    codes = Q.encode(src.emb(spark, d), model)
    numbers = codes.select(F.posexplode(E.unpack([F.col("w0")], TINY)).alias("m", "i"))
    return numbers.groupBy(F.col("m").cast("int").alias("m"), F.col("i").cast("int").alias("i")).agg(F.count("*").alias("n"))


# objectives on fixed numberings

_PAIRS = K.with_(
    *COMMON,
    f"dist AS (SELECT a.m, a.i, b.i AS j, sqrt({K.sqd('a.c', 'b.c', 4)}) AS d FROM cb a JOIN cb b USING (m))",
    "ms AS (SELECT m, avg(d) AS mu, stddev_pop(d) AS sd FROM dist GROUP BY m)",
    "sc AS (SELECT m, i, j, d, 2 + (d - mu) * 1 / sd AS f FROM dist JOIN ms USING (m))",
)


def _h(numbering: str, a: str = "i", b: str = "j") -> str:
    e = K.NUMBERINGS[numbering].format(K=16)
    return f"bit_count(xor(({e.replace('i', a)}), ({e.replace('i', b)})))::BIGINT" if numbering == "identity" else f"bit_count(xor({_num(numbering, a)}, {_num(numbering, b)}))::BIGINT"


def _num(numbering: str, v: str) -> str:
    return {"identity": v, "gray": f"xor({v}, {v} >> 1)", "affine": f"(5*{v}+3) % 16"}[numbering]


def _pi(numbering: str) -> np.ndarray:
    return {"identity": np.arange(16), "gray": A.gray(16), "affine": A.affine(16)}[numbering]


def _per_slice(spark: SparkSession, d: str, fn) -> DataFrame:
    _, model = _first(spark, d)
    return spark.createDataFrame([(m, float(fn(model.codebook[m]))) for m in range(TINY.M)], "m int, value double").select("m", F.round("value", 6).alias("value"))


@query("centroid_distances", _PAIRS + "SELECT m, i, j, round(d, 6) AS d FROM dist")
def centroid_distances(spark: SparkSession, d: str) -> DataFrame:
    book = Q.codebook_first(_split(spark, d).train, TINY)
    a, b = book.select("m", "i", F.col("centroid").alias("a")), book.select("m", F.col("i").alias("j"), F.col("centroid").alias("b"))
    return a.join(F.broadcast(b), "m").select(F.col("m").cast("int").alias("m"), F.col("i").cast("int").alias("i"), F.col("j").cast("int").alias("j"), F.round(F.sqrt(E.l2sq(F.col("a"), F.col("b"))), 6).alias("d"))


@query("hamming_scale", _PAIRS + "SELECT m, i, j, round(f, 6) AS f FROM sc")
def hamming_scale(spark: SparkSession, d: str) -> DataFrame:
    _, model = _first(spark, d)
    rows = [(m, i, j, float(f[i, j])) for m in range(16) for f in [A.hamming_scale(A.centroid_distances(model.codebook[m]), 4)] for i in range(16) for j in range(16)]
    return spark.createDataFrame(rows, "m int, i int, j int, f double").select("m", "i", "j", F.round("f", 6).alias("f"))


for _n in ("identity", "gray", "affine"):
    _hn = f"bit_count(xor({_num(_n, 'i')}, {_num(_n, 'j')}))::BIGINT"
    _hk = f"bit_count(xor({_num(_n, 'a.i')}, {_num(_n, 'a.j')}))"
    _hl = f"bit_count(xor({_num(_n, 'b.i')}, {_num(_n, 'b.j')}))"
    _dis = f"dis AS (SELECT a.m, a.i, a.j, a.d, count(*) FILTER (WHERE b.d > a.d AND {_hl} < {_hk}) AS r, greatest(count(*) FILTER (WHERE b.d < a.d), 1) AS rank FROM dist a JOIN dist b ON a.m = b.m AND a.i = b.i GROUP BY a.m, a.i, a.j, a.d)"
    _harm = "hm AS (SELECT n, coalesce(list_sum([1.0 / z for z in range(1, n + 1)]), 0)::DOUBLE AS l FROM range(17) t(n))"

    @query(f"loss_distance_{_n}", _PAIRS + f"SELECT m, round(sum(({_hn} - f) * ({_hn} - f)), 6) AS value FROM sc GROUP BY m")
    def loss_distance(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        return _per_slice(spark, d, lambda c: A.DistanceLoss(c, 4, None).full(_pi(n)))

    @query(f"loss_weighted_{_n}", _PAIRS + f"SELECT m, round(sum(pow(0.5, f) * ({_hn} - f) * ({_hn} - f)), 6) AS value FROM sc GROUP BY m")
    def loss_weighted(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        return _per_slice(spark, d, lambda c: A.DistanceLoss(c, 4, 0.5).full(_pi(n)))

    @query(f"loss_channel_{_n}", _PAIRS + f"SELECT m, round(sum(d * d) FILTER (WHERE {_hn} = 1), 6) AS value FROM dist GROUP BY m")
    def loss_channel(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        return _per_slice(spark, d, lambda c: A.loss_channel(_pi(n), A.centroid_distances(c)))

    @query(f"rank_disagreement_{_n}", _PAIRS.rstrip() + ", " + _dis + " SELECT m, i, j, r FROM dis")
    def rank_disagreement(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        _, model = _first(spark, d)
        rows = [(m, i, j, int(r[i, j])) for m in range(16) for r in [A.rank_disagreement(_pi(n), A.centroid_distances(model.codebook[m]))] for i in range(16) for j in range(16)]
        return spark.createDataFrame(rows, "m int, i int, j int, r bigint")

    @query(f"loss_rank_all_{_n}", _PAIRS.rstrip() + ", " + _dis + ", " + _harm + " SELECT m, round(sum(l / rank) FILTER (WHERE i <> j), 6) AS value FROM dis JOIN hm ON hm.n = dis.r GROUP BY m")
    def loss_rank_all(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        return _per_slice(spark, d, lambda c: A.RankLoss(c, 4).full(_pi(n)))

    @query(
        f"loss_rank_knn_{_n}",
        _PAIRS.rstrip() + ", " + _dis + ", " + _harm + ", nn AS (SELECT *, row_number() OVER (PARTITION BY m, i ORDER BY d, j) AS p FROM dis WHERE i <> j) SELECT m, round(sum(l), 6) AS value FROM nn JOIN hm ON hm.n = nn.r WHERE p <= 4 GROUP BY m",
    )
    def loss_rank_knn(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        return _per_slice(spark, d, lambda c: A.RankLoss(c, 4, "knn", 4).full(_pi(n)))

    @query(
        f"kendall_{_n}",
        _PAIRS + f"SELECT a.m, round(sum(sign(a.d - b.d) * sign({_hk} - {_hl}))::DOUBLE / greatest(count(*) FILTER (WHERE a.d <> b.d AND {_hk} <> {_hl}), 1), 6) AS value FROM dist a JOIN dist b ON a.m = b.m AND a.i = b.i GROUP BY a.m",
    )
    def kendall(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        return _per_slice(spark, d, lambda c: A.kendall_tau(_pi(n), A.centroid_distances(c)))


_SW = "(CASE {v} WHEN 3 THEN 9 WHEN 9 THEN 3 ELSE {v} END)"
_hi, _hj = _SW.format(v="i"), _SW.format(v="j")


@query(
    "swap_delta_distance",
    _PAIRS + f"SELECT m, round(sum(pow(0.5, f) * (pow(bit_count(xor({_hi}, {_hj})) - f, 2) - pow(bit_count(xor(i, j)) - f, 2))), 6) AS value FROM sc GROUP BY m",
)
def swap_delta_distance(spark: SparkSession, d: str) -> DataFrame:
    """The O(K) update against the difference of whole losses."""

    def delta(c: np.ndarray) -> float:
        loss = A.DistanceLoss(c, 4)
        return loss.delta(np.arange(16), 3, 9)

    return _per_slice(spark, d, delta)


# optimizers


def _trained(spark: SparkSession, d: str, construction: str = "dist_assigned", n_iter: int = 6000, restarts: int = 1) -> tuple[V.Split, CodeModel]:
    s = _split(spark, d)
    model = Q.train_pq(s.train, 16, 4, dims=64, seed=42)
    return s, (model if construction == "plain" else A.fit_assignment(spark, model, construction, n_iter=n_iter, restarts=restarts, seed=42)[0])


@query("rank_anneal_summary")
def rank_anneal_summary(spark: SparkSession, d: str) -> DataFrame:
    s = _split(spark, d)
    model = Q.train_pq(s.train, 16, 4, dims=64, seed=42)
    _, trace = A.fit_assignment(spark, model, "rank_assigned", n_iter=RANK, seed=42)
    return spark.createDataFrame(trace).groupBy("m").agg(F.min_by("loss", "iter").alias("first_loss"), F.max_by("loss", "iter").alias("best_loss"))


@query("optimizer_study")
def optimizer_study(spark: SparkSession, d: str) -> DataFrame:
    return X.optimizer_study(_split(spark, d).train, 64, 16, 4, n_iter=COOL, restarts=2)


@query("alpha_study")
def alpha_study(spark: SparkSession, d: str) -> DataFrame:
    s = _split(spark, d)
    return X.alpha_study(s, 64, 16, 4, [0.2, 0.3, 0.4, 0.5, 0.6], n_iter=COOL)


@query("convergence_study")
def convergence_study(spark: SparkSession, d: str) -> DataFrame:
    return X.convergence_study(_split(spark, d), 64, 32, 4, (0, 500, 2000, 5000, 10_000, COOL), tau=52)


# searches on fixed numberings

_ENC = (*COMMON, K.nearest(64, 16))


@query("exact_knn", K.with_(K.vectors(), K.splits(), f"p AS (SELECT qid, vec_id, {K.sqd('e', 'q', 64)} AS score FROM base, qry)") + K.top("p", 10))
def exact_knn(spark: SparkSession, d: str) -> DataFrame:
    s = _split(spark, d)
    return _round(S.exact_knn(s.query, s.base, 10))


@query("exact_knn_sql", K.with_(K.vectors(), K.splits(), f"p AS (SELECT qid, vec_id, {K.sqd('e', 'q', 64)} AS score FROM base, qry)") + K.top("p", 10))
def exact_knn_sql(spark: SparkSession, d: str) -> DataFrame:
    """The truth in plain expressions."""
    s = _split(spark, d)
    return _round(S.exact_knn(s.query, s.base, 10, engine="sql"))


@query("exact_range", K.with_(K.vectors(), K.splits()) + f"SELECT qid, vec_id, round({K.sqd('e', 'q', 64)}, 6) AS score FROM base, qry WHERE {K.sqd('e', 'q', 64)} <= 1.4")
def exact_range(spark: SparkSession, d: str) -> DataFrame:
    s = _split(spark, d)
    return S.exact_range(s.query, s.base, 1.4).select("qid", "vec_id", F.round("score", 6).alias("score"))


@query(
    "exact_filtered_knn",
    f"WITH l AS (SELECT doc_id AS vec_id, {_LETTER} AS e, lang FROM (SELECT doc_id, text AS t, lang FROM documents)), "
    f"p AS (SELECT a.vec_id AS qid, b.vec_id, {K.sqd('a.e', 'b.e', 24)} AS score FROM l a JOIN l b ON a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4 JOIN labels g ON g.doc_id = b.vec_id WHERE b.lang = 'en' AND g.quality = 1) "
    "SELECT qid, round(score, 6) AS score, row_number() OVER (PARTITION BY qid ORDER BY score, vec_id)::INTEGER AS rk FROM p QUALIFY rk <= 5",
)
def exact_filtered_knn(spark: SparkSession, d: str) -> DataFrame:
    s = V.split(src.letters(spark, d))
    return _round(X.filtered_knn(spark, d, s, 5)).select("qid", "score", "rk")


_ADC = K.with_(*_ENC, K.adc_pairs(64, 16)) + K.top("adc", 10)


@query("adc_knn", _ADC)
def adc_knn(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d)
    return _round(S.adc_knn(p, c, model, 10))


@query("adc_knn_gray", _ADC)
def adc_knn_gray(spark: SparkSession, d: str) -> DataFrame:
    """Look-up estimates don't depend on the numbering: the same oracle."""
    _, model, p, c = _ready(spark, d, "gray")
    return _round(S.adc_knn(p, c, model, 10))


@query("adc_knn_arrow", _ADC)
def adc_knn_arrow(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d)
    return _round(S.adc_knn_arrow(p, c, model, 10))


@query(
    "sdc_knn",
    K.with_(*_ENC, f"cc AS (SELECT a.m, a.i, b.i AS j, {K.sqd('a.c', 'b.c', 4)} AS d FROM cb a JOIN cb b USING (m))", "p AS (SELECT q.vec_id AS qid, b.vec_id, list_sum(list(d ORDER BY q.m)) AS score FROM enc q JOIN enc b USING (m) JOIN cc ON cc.m = q.m AND cc.i = q.i AND cc.j = b.i WHERE q.vec_id % 10 = 0 AND b.vec_id % 10 >= 4 GROUP BY 1, 2)")
    + K.top("p", 10),
)
def sdc_knn(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d)
    return _round(S.sdc_knn(p, c, model, 10))


for _n in ("identity", "gray"):

    @query(
        f"hamming_knn_{_n}",
        K.with_(*_ENC, K.words(4, _n), f"p AS (SELECT a.vec_id AS qid, b.vec_id, {K.ham('a.w', 'b.w')}::DOUBLE AS score FROM wrd a, wrd b WHERE a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4)") + K.top("p", 10),
    )
    def hamming_knn(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        _, model, p, c = _ready(spark, d, n)
        return _round(S.hamming_knn(p, c, model, 10))

    @query(
        f"two_stage_knn_{_n}" if _n != "gray" else "two_stage_knn",
        K.with_(*_ENC, K.words(4, _n), K.adc_pairs(64, 16), f"kept AS (SELECT adc.* FROM adc JOIN wrd a ON a.vec_id = qid JOIN wrd b ON b.vec_id = adc.vec_id WHERE {K.ham('a.w', 'b.w')} <= {TAU})") + K.top("kept", 10),
    )
    def two_stage_knn(spark: SparkSession, d: str, n: str = _n) -> DataFrame:
        _, model, p, c = _ready(spark, d, n)
        return _round(S.two_stage_knn(p, c, model, 10, TAU))


_MIS = "mm AS (SELECT q.vec_id AS qid, b.vec_id, count(*) FILTER (WHERE q.i <> b.i) AS h FROM enc q JOIN enc b USING (m) WHERE q.vec_id % 10 = 0 AND b.vec_id % 10 >= 4 GROUP BY 1, 2)"


@query("mismatch_knn", K.with_(*_ENC, _MIS) + K.top("mm", 10, "h::DOUBLE"))
def mismatch_knn(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d, "gray")
    return _round(S.mismatch_knn(p, c, model, 10))


@query("two_stage_mismatch", K.with_(*_ENC, _MIS, K.adc_pairs(64, 16), "kept AS (SELECT adc.* FROM adc JOIN mm USING (qid, vec_id) WHERE h <= 14)") + K.top("kept", 10))
def two_stage_mismatch(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d)
    return _round(S.two_stage_knn(p, c, model, 10, 14, by="mismatch"))


@query(
    "two_stage_rerank",
    K.with_(*_ENC, K.words(4), K.adc_pairs(64, 16), f"s AS (SELECT qid, adc.vec_id FROM adc JOIN wrd a ON a.vec_id = qid JOIN wrd b ON b.vec_id = adc.vec_id WHERE {K.ham('a.w', 'b.w')} <= {TAU} QUALIFY row_number() OVER (PARTITION BY qid ORDER BY score, adc.vec_id) <= 30)", f"p AS (SELECT s.qid, s.vec_id, {K.sqd('e', 'q', 64)} AS score FROM s JOIN base USING (vec_id) JOIN qry USING (qid))") + K.top("p", 10),
)
def two_stage_rerank(spark: SparkSession, d: str) -> DataFrame:
    s, model, p, c = _ready(spark, d)
    return _round(S.rerank(S.two_stage_knn(p, c, model, 30, TAU), s.query, s.base, 10))


@query("hamming_range", K.with_(*_ENC, K.words(4, "gray")) + f"SELECT a.vec_id AS qid, b.vec_id, {K.ham('a.w', 'b.w')}::INTEGER AS h FROM wrd a, wrd b WHERE a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4 AND {K.ham('a.w', 'b.w')} <= 22")
def hamming_range(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d, "gray")
    return S.hamming_range(p, c, model, 22)


@query("adc_range", K.with_(*_ENC, K.adc_pairs(64, 16)) + "SELECT qid, vec_id, round(score, 6) AS score FROM adc WHERE score <= 1.3")
def adc_range(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d)
    return S.adc_range(p, c, model, 1.3).select("qid", "vec_id", F.round("score", 6).alias("score"))


def _bits_knn(spark: SparkSession, d: str, model: B.BinaryModel) -> DataFrame:
    s = _split(spark, d)
    fake = CodeModel(B.bit_spec(model), np.zeros((0, 0, 0)))
    return _round(S.hamming_knn(B.encode_bits(s.query, model, "q", "qid"), B.encode_bits(s.base, model), fake, 10))


def _sign_sql() -> str:
    m = B.fit_sign_lsh(64, 32, 7).image.matrix
    rows = ", ".join(f"({j}, [" + ", ".join(repr(float(x)) for x in m[:, j]) + "])" for j in range(32))
    bits = f"r(j, c) AS (VALUES {rows}), s AS (SELECT vec_id, list(list_sum([e[z]*c[z] for z in range(1, 65)]) >= 0 ORDER BY j) AS b FROM v, r GROUP BY vec_id)"
    return K.with_(K.vectors(), bits, "p AS (SELECT a.vec_id AS qid, b.vec_id, list_sum([(a.b[z] <> b.b[z])::INTEGER for z in range(1, 33)])::DOUBLE AS score FROM s a, s b WHERE a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4)") + K.top("p", 10)


@query("lsh_knn", _sign_sql())
def lsh_knn(spark: SparkSession, d: str) -> DataFrame:
    return _bits_knn(spark, d, B.fit_sign_lsh(64, 32, 7))


# measures

_TRUE = f"true1 AS (SELECT qid, vec_id FROM (SELECT qid, vec_id, {K.sqd('e', 'q', 64)} AS s FROM base, qry) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) = 1)"


@query(
    "recall_table",
    K.with_(*_ENC, K.adc_pairs(64, 16), _TRUE, "rk AS (SELECT qid, vec_id, row_number() OVER (PARTITION BY qid ORDER BY score, vec_id) AS rk FROM adc)")
    + "SELECT r::INTEGER AS r, round(avg((rk <= r)::INTEGER), 6) AS recall FROM true1 JOIN rk USING (qid, vec_id), (VALUES (1), (10), (100)) t(r) GROUP BY r",
)
def recall_table(spark: SparkSession, d: str) -> DataFrame:
    s, model, p, c = _ready(spark, d)
    return R.recall_at(S.adc_knn(p, c, model, 100), S.exact_knn(s.query, s.base, 1)).select("r", F.round("recall", 6).alias("recall"))


@query(
    "intersection_at_k",
    K.with_(*_ENC, K.adc_pairs(64, 16), f"t AS (SELECT qid, vec_id FROM (SELECT qid, vec_id, {K.sqd('e', 'q', 64)} AS s FROM base, qry) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) <= 10)", "a AS (SELECT qid, vec_id FROM adc QUALIFY row_number() OVER (PARTITION BY qid ORDER BY score, vec_id) <= 10)")
    + "SELECT round(avg(n / 10), 6) AS intersection FROM (SELECT t.qid, count(a.vec_id) AS n FROM t LEFT JOIN a USING (qid, vec_id) GROUP BY t.qid)",
)
def intersection_at_k(spark: SparkSession, d: str) -> DataFrame:
    s, model, p, c = _ready(spark, d)
    return R.intersection_at(S.adc_knn(p, c, model, 10), S.exact_knn(s.query, s.base, 10), 10).select(F.round("intersection", 6).alias("intersection"))


@query(
    "coverage_table",
    K.with_(*_ENC, K.words(4, "gray"), _TRUE)
    + f"SELECT tau::INTEGER AS tau, round(avg(({K.ham('a.w', 'b.w')} <= tau)::INTEGER), 6) AS coverage FROM true1 t JOIN wrd a ON a.vec_id = t.qid JOIN wrd b ON b.vec_id = t.vec_id, (VALUES (16), (24), (32), (64)) x(tau) GROUP BY tau",
)
def coverage_table(spark: SparkSession, d: str) -> DataFrame:
    s, model, p, c = _ready(spark, d, "gray")
    return R.coverage(S.exact_knn(s.query, s.base, 1), c, p, model, [16, 24, 32, 64]).select("tau", F.round("coverage", 6).alias("coverage"))


_HIST = f"hh AS (SELECT {K.ham('a.w', 'b.w')} AS h, count(*) AS n FROM wrd a, wrd b WHERE a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4 GROUP BY 1)"


@query("tau_histogram", K.with_(*_ENC, K.words(4, "gray"), _HIST) + "SELECT h::INTEGER AS h, n, (sum(n) OVER (ORDER BY h))::BIGINT AS kept, round(sum(n) OVER (ORDER BY h) / sum(n) OVER (), 6) AS kept_share FROM hh")
def tau_histogram(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d, "gray")
    return C.hamming_histogram(p, c, model).select(F.col("h").cast("int").alias("h"), "n", "kept", F.round("kept_share", 6).alias("kept_share"))


@query("calibrate_tau", K.with_(*_ENC, K.words(4, "gray"), _HIST) + "SELECT max(h)::INTEGER AS tau FROM (SELECT h, sum(n) OVER (ORDER BY h) / sum(n) OVER () AS s FROM hh) WHERE s <= 0.05")
def calibrate_tau(spark: SparkSession, d: str) -> DataFrame:
    _, model, p, c = _ready(spark, d, "gray")
    return spark.createDataFrame([(C.calibrate_tau(p, c, model),)], "tau int")


@query(
    "tau_sweep",
    K.with_(*_ENC, K.words(4, "gray"), K.adc_pairs(64, 16), _TRUE, f"pr AS (SELECT adc.qid, adc.vec_id, score, {K.ham('a.w', 'b.w')} AS h FROM adc JOIN wrd a ON a.vec_id = qid JOIN wrd b ON b.vec_id = adc.vec_id)", "tt AS (SELECT pr.* FROM pr JOIN true1 USING (qid, vec_id))")
    + "SELECT tau::INTEGER AS tau, round(k / (SELECT count(*) FROM pr), 6) AS kept_share, round(hit / (SELECT count(*) FROM qry), 6) AS recall FROM (SELECT tau, (SELECT count(*) FROM pr WHERE h <= tau) AS k, "
    "(SELECT count(*) FROM tt WHERE h <= tau AND NOT EXISTS (SELECT 1 FROM pr WHERE pr.qid = tt.qid AND pr.h <= tau AND (pr.score < tt.score OR (pr.score = tt.score AND pr.vec_id < tt.vec_id)))) AS hit FROM range(65) r(tau))",
)
def tau_sweep(spark: SparkSession, d: str) -> DataFrame:
    s, model, p, c = _ready(spark, d, "gray")
    return R.tau_sweep(p, c, S.exact_knn(s.query, s.base, 1), model).select("tau", F.round("kept_share", 6).alias("kept_share"), F.round("recall", 6).alias("recall"))


@query(
    "correlation_study",
    K.with_(*_ENC, K.words(4, "gray"), K.adc_pairs(64, 16), f"pr AS (SELECT adc.qid, adc.vec_id, score, {K.ham('a.w', 'b.w')} AS h, {K.sqd('base.e', 'qry.q', 64)} AS d2 FROM adc JOIN wrd a ON a.vec_id = adc.qid JOIN wrd b ON b.vec_id = adc.vec_id JOIN base ON base.vec_id = adc.vec_id JOIN qry ON qry.qid = adc.qid)")
    + "SELECT 'adc' AS estimator, round(corr(d2, score), 6) AS pearson FROM pr UNION ALL SELECT 'hamming', round(corr(d2, h), 6) FROM pr",
)
def correlation_study(spark: SparkSession, d: str) -> DataFrame:
    s, model, p, c = _ready(spark, d, "gray")
    got = R.correlations(p, s.query, c, s.base, model, ranks=False)
    return got.where("estimator <> 'index_mismatch'").select("estimator", F.round("pearson", 6).alias("pearson"))


@query("one_bit_edges", _PAIRS + f"SELECT m, round(avg(d) FILTER (WHERE bit_count(xor({_num('gray', 'i')}, {_num('gray', 'j')})) = 1), 6) AS one_bit, round(avg(d) FILTER (WHERE i <> j), 6) AS all_pairs FROM dist GROUP BY m")
def one_bit_edges(spark: SparkSession, d: str) -> DataFrame:
    book = Q.codebook_first(_split(spark, d).train, TINY)
    number = book.select("m", "i", F.col("i").bitwiseXOR(F.shiftright("i", 1)).alias("code"))
    return R.one_bit_edges(book, number).select(F.col("m").cast("int").alias("m"), F.round("one_bit", 6).alias("one_bit"), F.round("all_pairs", 6).alias("all_pairs"))


@query("op_counts", K.with_(K.vectors(), K.splits()) + "SELECT (SELECT count(*) FROM qry) * (SELECT count(*) FROM base) * 1.0::DOUBLE AS word_xors, (SELECT count(*) FROM qry) * (SELECT count(*) FROM base) * 16.0::DOUBLE AS full_lut_adds")
def op_counts(spark: SparkSession, d: str) -> DataFrame:
    s = _split(spark, d)
    got = R.op_counts(s.query.count(), s.base.count(), CodeModel(TINY, np.zeros((16, 16, 4))), 0.05)
    return spark.createDataFrame([(got["word_xors"], got["full_lut_adds"])], "word_xors double, full_lut_adds double")


# coarse index


def _coarse(spark: SparkSession, d: str, **kw) -> tuple[V.Split, I.CoarseIndex]:
    s, model = _first(spark, d, "gray")
    return s, I.fit_multi_index(s.train, 64, 3, model, seed=1, **kw)


@query("ivf_search_all_cells", _ADC)
def ivf_search_all_cells(spark: SparkSession, d: str) -> DataFrame:
    """With all cells visited and no bit test the index gives the full scan's result."""
    s, ix = _coarse(spark, d)
    return _round(I.search_ivf(I.probe_cells(s.query, ix, 64), I.encode_cells(s.base, ix), ix, 10))


@query("coarse_study")
def coarse_study(spark: SparkSession, d: str) -> DataFrame:
    return X.coarse_study(_split(spark, d), 64, 16, 4, [1, 8, 64], [24, 64])


@query("pipeline_study")
def pipeline_study(spark: SparkSession, d: str) -> DataFrame:
    return X.pipeline_study(V.split(src.words(spark, d).cache()), 64, ["pq16", "mi2x3,pq16", "rot16_48,mi2x3,pq16"])


# experiments


#: Swaps of the ranking objective in registered queries; its update costs some twenty times as much as the distance's.
RANK = 10_000


@query("ablation_grid")
def ablation_grid(spark: SparkSession, d: str) -> DataFrame:
    """All constructions and estimators, five seeds, 8 bytes."""
    return X.ablation_grid(_split(spark, d), 64, 16, 4, n_iter={"dist_assigned": COOL, "rank_assigned": RANK})


@query("ablation_cube")
def ablation_cube(spark: SparkSession, d: str) -> DataFrame:
    """Mean and deviation over seeds, with totals by construction and by estimator, at 16 bytes."""
    runs = X.ablation_grid(_split(spark, d), 64, 32, 4, n_iter={"dist_assigned": COOL}, constructions=("plain", "dist_assigned"), seeds=(1, 2, 3))
    return runs.cube("construction", "estimator").agg(F.avg("r100").alias("r100"), F.stddev_samp("r100").alias("r100_std"), F.count("*").alias("n"))


@query("ablation_summary")
def ablation_summary(spark: SparkSession, d: str) -> DataFrame:
    """Means, deviations and milliseconds a query over five seeds, at 16 bytes of 4-bit numbers."""
    runs = X.ablation_grid(_split(spark, d), 64, 32, 4, n_iter={"dist_assigned": COOL}, constructions=("plain", "dist_assigned"), timing=True)
    return R.summarise_runs(runs, ["construction", "estimator"], ["r1", "r10", "r100", "ms"])


@query("ablation_bytes")
def ablation_bytes(spark: SparkSession, d: str) -> DataFrame:
    """16 bytes of 8-bit numbers, on word vectors: 256 centroids a slice need as many training rows."""
    return X.ablation_grid(V.split(src.words(spark, d).cache()), 64, 16, 8, n_iter={"dist_assigned": 100_000}, constructions=("plain", "dist_assigned"), seeds=(1,))


@query("training_time")
def training_time(spark: SparkSession, d: str) -> DataFrame:
    """Seconds a slice of learning a numbering, by objective, beside its loss before and after."""
    model = Q.train_pq(_split(spark, d).train, 16, 4, dims=64, seed=42)
    traces = [spark.createDataFrame(A.fit_assignment(spark, model, c, n_iter=n, seed=42)[1]).withColumns({"objective": F.lit(c), "n_iter": F.lit(n)}) for c, n in (("dist_assigned", COOL), ("rank_assigned", 1000))]
    ends = traces[0].unionAll(traces[1]).groupBy("objective", "n_iter", "m").agg(F.min_by("loss", "iter").alias("first"), F.max_by("loss", "iter").alias("last"), F.max("seconds").alias("s"))
    return ends.groupBy("objective", "n_iter").agg(F.sum("first").alias("loss_before"), F.sum("last").alias("loss_after"), F.avg("s").alias("seconds_a_slice"), (F.avg("s") / F.first("n_iter") * 1e6).alias("microseconds_a_swap"))


@query("toy_plane")
def toy_plane(spark: SparkSession, d: str) -> DataFrame:
    return X.toy_plane(src.plane(spark, d), b=6, n_iter=60_000)


_FL = (
    f"l AS MATERIALIZED (SELECT vec_id, e, lang, source, n_chars FROM (SELECT doc_id AS vec_id, {_LETTER} AS e, lang, source, n_chars FROM (SELECT *, text AS t FROM documents)))",
    f"p AS MATERIALIZED (SELECT a.vec_id AS qid, b.vec_id, b.lang, b.source, b.n_chars, {K.sqd('a.e', 'b.e', 24)} AS s FROM l a JOIN l b ON a.vec_id % 10 = 0 AND b.vec_id % 10 >= 4)",
    "al AS (SELECT qid, vec_id FROM p QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) <= 10)",
)


def _filtered(name: str, cond: str) -> str:
    top = f"(SELECT qid, vec_id FROM p WHERE {cond} QUALIFY row_number() OVER (PARTITION BY qid ORDER BY s, vec_id) <= 5)"
    return (
        f"SELECT '{name}' AS predicate, round((SELECT count(*) FROM l WHERE vec_id % 10 >= 4 AND {cond}) / (SELECT count(*) FROM l WHERE vec_id % 10 >= 4), 6) AS selectivity, "
        f"round((SELECT count(*) FROM {top} JOIN al USING (qid, vec_id)) / greatest((SELECT count(*) FROM {top}), 1), 6) AS post_filter_recall"
    )


@query("filtered_study", K.with_(*_FL) + " UNION ALL ".join(_filtered(n, c) for n, c in X.PREDICATES))
def filtered_study(spark: SparkSession, d: str) -> DataFrame:
    got = X.filtered_study(spark, d)
    return got.select("predicate", *[F.round(c, 6).alias(c) for c in ("selectivity", "post_filter_recall")])


@query("scale_rate")
def scale_rate(spark: SparkSession, d: str) -> DataFrame:
    """Kept share of the bit test over all order lines."""
    return X.scale_study(spark, d)


# graph

_EDGES = f"ed AS (SELECT a.vec_id AS src, b.vec_id AS dst, {K.sqd('a.e', 'b.e', 64)} AS dist FROM v a, v b WHERE a.vec_id <> b.vec_id QUALIFY row_number() OVER (PARTITION BY a.vec_id ORDER BY dist, b.vec_id) <= 5)"


def _graph(spark: SparkSession, d: str) -> DataFrame:
    """The true graph, kept: what follows reads its few edges more than once."""
    return G.knn_graph_exact(src.emb(spark, d), 5).cache()


@query("knn_graph_exact", K.with_(K.vectors(), _EDGES) + "SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dist, dst)::INTEGER AS rk, round(dist, 6) AS dist FROM ed")
def knn_graph_exact(spark: SparkSession, d: str) -> DataFrame:
    return _graph(spark, d).select("src", "dst", F.col("rk").cast("int").alias("rk"), F.round("dist", 6).alias("dist"))


@query("graph_stats", K.with_(K.vectors(), _EDGES) + "SELECT count(*) AS edges, count(DISTINCT src) AS nodes, (SELECT max(c) FROM (SELECT count(*) AS c FROM ed GROUP BY dst)) AS max_in_degree, (SELECT count(*) FROM ed a JOIN ed b ON a.src = b.dst AND a.dst = b.src) AS mutual FROM ed")
def graph_stats(spark: SparkSession, d: str) -> DataFrame:
    return G.graph_stats(_graph(spark, d))


_SYM = "sy AS (SELECT src, dst FROM ed UNION SELECT dst, src FROM ed), dg AS (SELECT src, count(*) AS n FROM sy GROUP BY src)"


@query("walk_step", K.with_(K.vectors(), _EDGES, _SYM) + "SELECT dst AS node, round(sum(1.0 / n) / (SELECT count(*) FROM v), 9) AS p FROM sy JOIN dg USING (src) GROUP BY dst")
def walk_step(spark: SparkSession, d: str) -> DataFrame:
    g = _graph(spark, d)
    nodes = g.select(F.col("src").alias("node")).distinct()
    p = nodes.withColumn("p", F.lit(1.0) / g.select("src").distinct().count())
    return G.walk_step(p, G.transitions(g), nodes).select("node", F.round("p", 9).alias("p"))


@query("stationary", K.with_(K.vectors(), _EDGES, _SYM) + "SELECT src AS node, round(n / sum(n) OVER (), 5) AS p FROM dg")
def stationary(spark: SparkSession, d: str) -> DataFrame:
    """On a symmetric graph the walk ends in proportion to degrees: a closed form to hold it against."""
    return G.stationary(_with_dir(_graph(spark, d)), tol=1e-5, max_iter=60).select("node", F.round("p", 5).alias("p"))


def _with_dir(df: DataFrame) -> DataFrame:
    from twoview.streaming.streams import scratch

    spark = df.sparkSession
    if spark.conf.get("spark.checkpoint.dir", None) is None:
        spark.sparkContext.setCheckpointDir(scratch(spark))
    return df


_MODES = K.with_(K.vectors(), _EDGES, _SYM, "pr AS (SELECT src AS node, n AS p FROM dg)", "bs AS (SELECT ed.src AS node, max(pr.p) AS top, arg_min(ed.dst, (-pr.p) * 1000000 + ed.dst) AS who FROM ed JOIN pr ON pr.node = ed.dst GROUP BY ed.src)")


@query("modes", _MODES + "SELECT node, (p > top OR (p = top AND node < who)) AS is_mode FROM pr JOIN bs USING (node)")
def modes(spark: SparkSession, d: str) -> DataFrame:
    """Local maxima of degree, which is what the walk of a symmetric graph ends in."""
    g = _graph(spark, d)
    e = g.select("src", "dst").union(g.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()
    p = e.groupBy(F.col("src").alias("node")).agg(F.count("*").cast("double").alias("p"))
    return G.modes(g, p).select("node", "is_mode")


@query("mode_gallery", _MODES + "SELECT pr.node, round(pr.p / (SELECT sum(p) FROM pr), 9) AS p, g.rk::INTEGER AS rk, g.dst, round(g.dist, 6) AS dist FROM pr JOIN bs USING (node) JOIN (SELECT *, row_number() OVER (PARTITION BY src ORDER BY dist, dst) AS rk FROM ed) g ON g.src = pr.node WHERE (pr.p > top OR (pr.p = top AND pr.node < who)) AND g.rk <= 3")
def mode_gallery(spark: SparkSession, d: str) -> DataFrame:
    g = _with_dir(_graph(spark, d))
    got = G.mode_gallery(g, G.modes(g, G.settled(g)), 3)
    return got.select("node", F.round("p", 9).alias("p"), F.col("rk").cast("int").alias("rk"), "dst", F.round("dist", 6).alias("dist"))


@query("graph_study")
def graph_study(spark: SparkSession, d: str) -> DataFrame:
    return X.graph_study(_with_dir(src.emb(spark, d)), 64, 16, 4, k=10, n_probe=16)
