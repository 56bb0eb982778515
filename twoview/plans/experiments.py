"""Experiment drivers: each gives a table of settings and measures.

Constructions are compared at an equal share of kept pairs, never at an equal threshold, since renumbering
changes how distances spread.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twoview.operators import assignment as A
from twoview.operators import binary as B
from twoview.operators import calibrate as C
from twoview.operators import coarse as I
from twoview.operators import graph as G
from twoview.operators import measure as R
from twoview.operators import quantize as Q
from twoview.operators import search as S
from twoview.operators import vectors as V
from twoview.operators.model import CodeModel
from twoview.sources import vectors as src

Row = tuple


def _recalls(result: DataFrame, truth: DataFrame) -> dict[int, float]:
    """Recall by rank, against a truth that is kept; its one neighbour a query is sent to the lists, whose other rows are not dealt out."""
    first = truth.where("rk = 1").select("qid", "vec_id")
    if first.count() * 64 <= S.BROADCAST_BYTES:
        result = result.join(F.broadcast(first), ["qid", "vec_id"], "left_semi")
    return {r.r: r.recall for r in R.recall_at(result, truth).collect()}


def ablation_grid(
    split: V.Split, dims: int, M: int, b: int, *, constructions: tuple[str, ...] = ("plain", "dist_assigned", "rank_assigned"), seeds: tuple[int, ...] = (1, 2, 3, 4, 5),
    n_iter: dict[str, int] | None = None, keep: float = 0.05, k: int = 100, timing: bool = False,
) -> DataFrame:
    """Recall of every construction and estimator, and of the baselines, by seed; summarise_runs gives means and deviations."""
    spark = split.base.sparkSession
    n_iter = n_iter or {}
    truth = S.exact_knn(split.query, split.base, 1).cache()
    n_queries = split.query.count()
    rows: list[Row] = []

    def add(seed: int, construction: str, estimator: str, tau: int | None, make) -> None:
        rec = _recalls(make(), truth)
        ms = 1000 * R.timed(make) / max(n_queries, 1) if timing else None
        rows.append((seed, construction, estimator, tau, rec[1], rec[10], rec[100], ms))

    for seed in seeds:
        plain = Q.train_pq(split.train, M, b, dims=dims, seed=seed)
        for construction in constructions:
            model = plain if construction == "plain" else A.fit_assignment(spark, plain, construction, n_iter=n_iter.get(construction, 500_000), seed=seed)[0]
            p, c = S.prepare_queries(split.query, model), Q.encode(split.base, model).cache()  # tables are made anew where they are used
            sample = S.prepare_queries(split.train, model, lut=False).cache()
            tau = C.calibrate_tau(sample, c, model, keep)
            sample.unpersist()
            add(seed, construction, "hamming", None, lambda p=p, c=c, m=model: S.scan_knn(p, c, m, k, "hamming", n_queries=n_queries))
            add(seed, construction, "two_stage", tau, lambda p=p, c=c, m=model, t=tau: S.scan_knn(p, c, m, k, tau=t, n_queries=n_queries))
            if construction == "plain":
                add(seed, construction, "adc", None, lambda p=p, c=c, m=model: S.scan_knn(p, c, m, k, n_queries=n_queries))
                add(seed, construction, "index_mismatch", None, lambda p=p, c=c, m=model: S.scan_knn(p, c, m, k, "mismatch", n_queries=n_queries))
            c.unpersist()
        for name, bits in (("lsh", B.fit_sign_lsh(dims, M * b, seed)), ("itq", B.fit_itq(split.train, dims, M * b, seed=seed))):
            fake = CodeModel(B.bit_spec(bits), np.zeros((0, 0, 0)))
            q, c = B.encode_bits(split.query, bits, "q", "qid"), B.encode_bits(split.base, bits)
            add(seed, name, "hamming", None, lambda q=q, c=c, m=fake: S.scan_knn(q, c, m, k, "hamming", n_queries=n_queries))
    truth.unpersist()
    return spark.createDataFrame(rows, "seed int, construction string, estimator string, tau int, r1 double, r10 double, r100 double, ms double")


def toy_plane(plane: DataFrame, b: int = 6, n_iter: int = 20_000, seed: int = 0) -> DataFrame:
    """Mean distance of centroids one bit apart before and after renumbering, for points of a plane."""
    spark = plane.sparkSession
    model = Q.train_pq(plane, 1, b, dims=2, seed=seed)
    better, _ = A.fit_assignment(spark, model, "dist_assigned", n_iter=n_iter, seed=seed)
    h = A.hamming_table(model.spec.K)
    rows = []
    for name, m in (("before", model), ("after", better)):
        d = A.centroid_distances(m.codebook[0])
        rows.append((name, float(d[h == 1].mean()), float(d[h > 0].mean())))
    return spark.createDataFrame(rows, "numbering string, one_bit double, all_pairs double")


def optimizer_study(train: DataFrame, dims: int, M: int, b: int, n_iter: int = 20_000, restarts: int = 2, seed: int = 0) -> DataFrame:
    """Loss of plain, greedy and annealed numberings."""
    spark = train.sparkSession
    model = Q.train_pq(train, M, b, dims=dims, seed=seed)
    start = sum(A.DistanceLoss(model.codebook[m], b).full(np.arange(model.spec.K)) for m in range(M))
    greedy = A.fit_assignment(spark, model, optimizer="greedy", seed=seed)[0].info["loss"]
    greedy2 = A.fit_assignment(spark, model, optimizer="greedy", restarts=restarts, seed=seed)[0].info["loss"]
    annealed = A.fit_assignment(spark, model, n_iter=n_iter, restarts=restarts, seed=seed)[0].info["loss"]
    return spark.createDataFrame([("plain", float(start)), ("greedy", greedy), ("greedy_restarts", greedy2), ("anneal", annealed)], "optimizer string, loss double")


def alpha_study(split: V.Split, dims: int, M: int, b: int, alphas: list[float], n_iter: int = 20_000, seed: int = 0, keep: float = 0.05) -> DataFrame:
    """Recall of the two stages for several weight bases."""
    spark = split.base.sparkSession
    truth = S.exact_knn(split.query, split.base, 1).cache()
    plain = Q.train_pq(split.train, M, b, dims=dims, seed=seed)
    rows = []
    for alpha in alphas:
        model, _ = A.fit_assignment(spark, plain, alpha=alpha, n_iter=n_iter, seed=seed)
        p, c = S.prepare_queries(split.query, model), Q.encode(split.base, model)
        tau = C.calibrate_tau(S.prepare_queries(split.train, model), c, model, keep)
        rec = _recalls(S.two_stage_knn(p, c, model, 100, tau), truth)
        rows.append((float(alpha), tau, rec[1], rec[10], rec[100]))
    truth.unpersist()
    return spark.createDataFrame(rows, "alpha double, tau int, r1 double, r10 double, r100 double")


def convergence_study(split: V.Split, dims: int, M: int, b: int, checkpoints: tuple[int, ...], seed: int = 0, keep: float = 0.05, tau: int | None = None) -> DataFrame:
    """Loss and recall of the best numbering found up to each number of iterations, at one threshold, or at the share keep."""
    spark = split.base.sparkSession
    truth = S.exact_knn(split.query, split.base, 1).cache()
    model = Q.train_pq(split.train, M, b, dims=dims, seed=seed)
    shots = A.fit_assignment(spark, model, n_iter=max(checkpoints), seed=seed, snapshots=checkpoints)[0].info["snapshots"]
    rows = []
    for it in checkpoints:
        pi = shots[it]
        loss = sum(A.DistanceLoss(model.codebook[m], b).full(pi[m]) for m in range(M))
        numbered = model.relabelled(pi, "dist_assigned")
        p, c = S.prepare_queries(split.query, numbered), Q.encode(split.base, numbered)
        at = C.calibrate_tau(S.prepare_queries(split.train, numbered), c, numbered, keep) if tau is None else tau
        rec = _recalls(S.two_stage_knn(p, c, numbered, 100, at), truth)
        rows.append((it, float(loss), at, rec[1], rec[100]))
    truth.unpersist()
    return spark.createDataFrame(rows, "iter int, loss double, tau int, r1 double, r100 double")


def coarse_study(split: V.Split, dims: int, M: int, b: int, n_probes: list[int], taus: list[int], c: int = 3, seed: int = 0) -> DataFrame:
    """Candidates, look-ups, recall and the share of true neighbours that stay, by cells visited and threshold."""
    model = Q.train_pq(split.train, M, b, dims=dims, seed=seed)
    ix = I.fit_multi_index(split.train, dims, c, model, seed=seed)
    truth = S.exact_knn(split.query, split.base, 1)
    return I.autotune(split.query, truth, I.encode_cells(split.base, ix), ix, n_probes, taus)


def pipeline_study(split: V.Split, dims: int, specs: list[str], b: int = 4, n_iter: int = 30_000) -> DataFrame:
    """Written specs with their bytes a code and recall."""
    spark = split.base.sparkSession
    truth = S.exact_knn(split.query, split.base, 1).cache()
    rows = []
    for text in specs:
        got, _ = I.fit_pipeline(split.train, dims, text, b, n_iter=n_iter)
        model = got.codes if isinstance(got, I.CoarseIndex) else got
        rotation = model.info.get("rotation")
        base = V.apply_map(split.base, rotation) if rotation else split.base
        query = V.apply_map(split.query, rotation) if rotation else split.query
        if isinstance(got, I.CoarseIndex):
            res = I.search_ivf_dealt(query, I.encode_cells(base, got), got, 100, max(1, got.n_cells // 4))
        else:
            res = S.scan_knn(S.prepare_queries(query, model), Q.encode(base, model), model, 100)
        rec = _recalls(res, truth)
        rows.append((text, model.spec.code_bytes, rec[1], rec[10], rec[100]))
    truth.unpersist()
    return spark.createDataFrame(rows, "spec string, bytes int, r1 double, r10 double, r100 double")


def graph_study(vectors: DataFrame, dims: int, M: int, b: int, k: int, n_probe: int, tau: int | None = None, seed: int = 0) -> DataFrame:
    """Graph from the index, before and after a round of neighbours' neighbours, against the true one; number of modes."""
    spark = vectors.sparkSession
    train = vectors.where(F.pmod("vec_id", F.lit(10)).between(1, 3))
    ix = I.fit_multi_index(train, dims, 3, Q.train_pq(train, M, b, dims=dims, seed=seed), seed=seed)
    graph = G.knn_graph(vectors, ix, k, n_probe, tau).cache()
    truth = G.knn_graph_exact(vectors, k).cache()
    rows = []
    refined = G.graph_descent(graph, vectors, k).cache()  # stats read it five times
    for name, g in (("index", graph), ("refined", refined)):
        st = G.graph_stats(g, truth).first()
        rows.append((name, int(st.edges), st.true_found / max(st.true_edges, 1), int(st.mutual)))
    p = G.settled(graph).cache()
    n_modes = G.modes(graph, p).where("is_mode").count()
    total = p.agg(F.sum("p").alias("s")).first().s
    p.unpersist()
    refined.unpersist()
    graph.unpersist()
    truth.unpersist()
    return spark.createDataFrame([(*r, n_modes, float(total)) for r in rows], "graph string, edges bigint, recall double, mutual bigint, n_modes int, mass double")


def filtered_knn(spark: SparkSession, sf_dir: str, split: V.Split, k: int) -> DataFrame:
    """Nearest among English documents labelled good: the attributes cut the base before any distance."""
    docs = src.read_table(spark, sf_dir, "documents").where("lang = 'en'").select(F.col("doc_id").alias("vec_id"))
    good = src.read_table(spark, sf_dir, "labels").where("quality = 1").select(F.col("doc_id").alias("vec_id"))
    base = split.base.join(docs, "vec_id", "left_semi").join(good, "vec_id", "left_semi")
    return S.exact_knn(split.query, base, k)


PREDICATES = (("en", "lang = 'en'"), ("long", "n_chars > 3000"), ("de_src1", "lang = 'de' AND source = 'src1'"))


def filtered_study(spark: SparkSession, sf_dir: str, k: int = 5) -> DataFrame:
    """Filter before or after the search: share of the base left, and how much of the true filtered list is found."""
    letters = src.letters(spark, sf_dir).cache()  # texts are read once
    split = V.split(letters)
    docs = src.read_table(spark, sf_dir, "documents")
    n = split.base.count()
    every = S.exact_knn(split.query, split.base, 2 * k).cache()
    rows = []
    for name, cond in PREDICATES:
        ids = docs.where(cond).select(F.col("doc_id").alias("vec_id"))
        base = split.base.join(ids, "vec_id", "left_semi").cache()
        truth = S.exact_knn(split.query, base, k).cache()
        post = every.join(ids, "vec_id", "left_semi")
        found = post.join(truth.select("qid", "vec_id"), ["qid", "vec_id"], "left_semi").count()
        rows.append((name, base.count() / max(n, 1), found / max(truth.count(), 1)))
        base.unpersist()
        truth.unpersist()
    every.unpersist()
    letters.unpersist()
    return spark.createDataFrame(rows, "predicate string, selectivity double, post_filter_recall double")


def scale_study(spark: SparkSession, sf_dir: str, n_queries: int = 20, tau: int = 6) -> DataFrame:
    """Rows scanned and share kept by the bit test over all order lines, for a fixed number of queries."""
    v = src.lines(spark, sf_dir)
    sample = V.training_sample(v, 5000)
    model = Q.train_pq(sample, 4, 4, dims=8, seed=0)
    model, _ = A.fit_assignment(spark, model, n_iter=30_000)
    codes = Q.encode(v, model)
    q = S.prepare_queries(sample.orderBy("vec_id").limit(n_queries), model)
    kept = S.survivors(q, codes, model, tau, lut=False).agg(F.count("*").alias("kept"))
    return codes.agg(F.count("*").alias("n_codes")).crossJoin(kept).select("n_codes", "kept", (F.col("kept") / F.col("n_codes") / n_queries).alias("kept_share"))
