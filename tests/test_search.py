import numpy as np
import pytest
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
from twoview.operators.model import ModelSpec, pack_words
from twoview.sources import vectors as src

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def world(spark):
    s = V.split(src.emb(spark, D))
    model = Q.train_pq(s.train, 16, 4, dims=64, seed=1)
    better, trace = A.fit_assignment(spark, model, n_iter=3000, seed=1)
    return s, model, better, trace


def rows(df):
    return sorted((r.qid, r.rk, r.vec_id, round(r.score, 9)) for r in df.collect())


def test_look_ups_ignore_numbering_and_match_decoding(spark, world):
    s, model, better, _ = world
    a = rows(S.adc_knn(S.prepare_queries(s.query, model), Q.encode(s.base, model), model, 5))
    b = rows(S.adc_knn(S.prepare_queries(s.query, better), Q.encode(s.base, better), better, 5))
    assert a == b
    ids, x = V.collect_matrix(s.base)
    qids, q = V.collect_matrix(s.query)
    back = model.decode(model.encode(x))
    d = ((q[:, None] - back[None]) ** 2).sum(2)
    for qid, rk, vec, score in a:
        i, j = np.flatnonzero(qids == qid)[0], np.flatnonzero(ids == vec)[0]
        assert np.isclose(d[i, j], score) and (d[i] < score - 1e-9).sum() < rk


def test_two_stages_nest(spark, world):
    s, _, m, _ = world
    p, c = S.prepare_queries(s.query, m).cache(), Q.encode(s.base, m).cache()
    assert rows(S.two_stage_knn(p, c, m, 7, 64)) == rows(S.adc_knn(p, c, m, 7)) == rows(S.adc_knn_arrow(p, c, m, 7))
    assert S.two_stage_knn(p, c, m, 7, -1).count() == 0
    kept = [{(r.qid, r.vec_id) for r in S.hamming_range(p, c, m, t).collect()} for t in (18, 22, 26)]
    assert kept[0] <= kept[1] <= kept[2]
    assert {(r.qid, r.vec_id) for r in S.survivors(p, c, m, 22, strict=True, lut=False).collect()} <= kept[1]
    both = c.crossJoin(p).select(E.hamming([F.col("w0")], [F.col("q0")]).alias("h"), E.mismatch([F.col("w0")], [F.col("q0")], m.spec).alias("n"))
    assert both.where("h < n OR h > 4 * n").isEmpty()
    assert S.two_stage_at_least(p, c, m, 5, 10, 5).groupBy("qid").count().where("count < 5").isEmpty()
    one = S.search_one(V.lowest_ids(s.query, 1)[1][0], c, m, 5, 64).collect()
    first = min(r.qid for r in p.select("qid").collect())
    assert [r.vec_id for r in one] == [v for q, _, v, _ in rows(S.adc_knn(p, c, m, 5)) if q == first]


def test_threshold_sweep_matches_direct_filters(spark, world):
    s, _, m, _ = world
    p, c = S.prepare_queries(s.query, m).cache(), Q.encode(s.base, m).cache()
    truth = S.exact_knn(s.query, s.base, 1).cache()
    sweep = {r.tau: r for r in R.tau_sweep(p, c, truth, m).collect()}
    n = s.query.count() * s.base.count()
    for t in (20, 26, 64):
        direct = {r.r: r.recall for r in R.recall_at(S.two_stage_knn(p, c, m, 1, t), truth, (1,)).collect()}[1]
        assert np.isclose(sweep[t].recall, direct)
        assert np.isclose(sweep[t].kept_share, S.hamming_range(p, c, m, t).count() / n)
    shares = [sweep[t].kept_share for t in range(65)]
    assert shares == sorted(shares) and shares[-1] == 1
    tau = C.calibrate_tau(p, c, m, 0.05)
    assert sweep[tau].kept_share <= 0.05 < sweep[tau + 1].kept_share


def test_exact_forms_agree(spark, world):
    s, *_ = world
    assert rows(S.exact_knn(s.query, s.base, 5)) == rows(S.exact_knn_blas(s.query, s.base, 5))


def test_index_over_all_cells_is_the_full_scan(spark, world):
    s, model, _, _ = world
    p, c = S.prepare_queries(s.query, model), Q.encode(s.base, model)
    full = rows(S.adc_knn(p, c, model, 5))
    for parts in (1, 2):
        ix = I.fit_multi_index(s.train, 64, 2, model, parts=parts, seed=0)
        coded = I.encode_cells(s.base, ix)
        assert rows(I.search_ivf(I.probe_cells(s.query, ix, ix.n_cells), coded, ix, 5)) == full
    sizes = {r.cell: r.n for r in coded.groupBy("cell").agg(F.count("*").alias("n")).collect()}
    few = I.probe_cells(s.query, ix, 16, quota=30, sizes=sizes)
    got = few.join(coded, "cell").groupBy("qid").count().agg(F.min("count").alias("m")).first().m
    assert got >= 30


def test_walk_over_lists_gives_the_sorted_prefix(spark):
    rng = np.random.default_rng(0)
    for _ in range(30):
        t = [np.round(rng.random(8), 1) for _ in range(2)]
        every = sorted((float(t[0][i]) + float(t[1][j]), i * 8 + j) for i in range(8) for j in range(8))
        assert I.probe_order(t, 20) == every[:20]
    t = spark.createDataFrame([(1, t[0].tolist(), t[1].tolist())], "qid bigint, d_u array<double>, d_v array<double>")
    assert [r.cell for r in I.probe_cells_sql(t, 20).orderBy("ord").collect()] == [c for _, c in every[:20]]


def test_orderings_of_methods(spark):
    """What wins, on structured vectors and at an equal share of kept pairs."""
    s = V.split(src.words(spark, "/root/testdata/sf0.01"))
    truth = S.exact_knn(s.query, s.base, 1).cache()
    plain = Q.train_pq(s.train, 16, 4, dims=64, seed=3)
    got = {}
    for name, m in (("plain", plain), ("dist", A.fit_assignment(spark, plain, n_iter=6000, seed=3)[0])):
        p, c = S.prepare_queries(s.query, m).cache(), Q.encode(s.base, m).cache()
        tau = C.calibrate_tau(p, c, m, 0.05)
        for est, r in (("two_stage", S.two_stage_knn(p, c, m, 100, tau)), ("hamming", S.hamming_knn(p, c, m, 100)), ("adc", S.adc_knn(p, c, m, 100))):
            got[name, est] = {x.r: x.recall for x in R.recall_at(r, truth).collect()}
    assert got["plain", "adc"] == got["dist", "adc"]
    assert got["dist", "two_stage"][100] > got["plain", "two_stage"][100]
    assert got["dist", "hamming"][100] > got["plain", "hamming"][100]
    assert got["dist", "adc"][100] >= got["dist", "two_stage"][100]


def test_training_engines_and_errors(spark, world):
    s, *_ = world
    a = Q.train_pq(s.train, 16, 4, dims=64, seed=1, iters=3)
    b = Q.train_pq(s.train, 16, 4, dims=64, seed=1, iters=3, engine="grouped")
    assert np.allclose(a.codebook, b.codebook)
    start = Q.train_pq(s.train, 16, 4, dims=64, init="first", iters=0)
    c = Q.lloyd_distributed(s.train, start, 3)
    err = lambda m: Q.reconstruction_error(s.train, m).agg(F.sum("mse")).first()[0]
    assert err(c) < err(start)
    with pytest.raises(ValueError, match="training rows"):
        Q.train_pq(s.train, 8, 8, dims=64)
    x = np.repeat(np.arange(3.0), 10)[:, None]
    assert np.isfinite(Q.kmeans(x, 8, seed=0)).all()


def test_rotations(spark, world):
    s, *_ = world
    r = L.random_rotation(64, 5)
    assert np.allclose(r.matrix.T @ r.matrix, np.eye(64))
    pca = L.fit_pca(s.train, 64, 8)
    _, x = V.collect_matrix(s.train)
    u, sv, vt = np.linalg.svd(x - x.mean(0), full_matrices=False)
    assert np.allclose(np.abs(np.sum(pca.matrix * vt[:8].T, 0)), 1, atol=1e-6)
    m = L.fit_rotation_pq(s.train, 64, 8, 4, 32, iters=2)
    assert m.spec.D == 32 and np.allclose(m.before.matrix.T @ m.before.matrix, np.eye(32), atol=1e-6)
    sql = V.apply_map(s.query, r, engine="sql").orderBy("vec_id").collect()
    arrow = V.apply_map(s.query, r).orderBy("vec_id").collect()
    assert np.allclose([a.embedding for a in sql], [a.embedding for a in arrow])


def test_binary_codes(spark, world):
    s, *_ = world
    assert np.allclose(B.fit_sign_lsh(64, 64, 1).image.matrix.T @ B.fit_sign_lsh(64, 64, 1).image.matrix, np.eye(64))
    itq = B.fit_itq(s.train, 64, 96, iters=5)
    assert itq.image.matrix.shape == (64, 96) and B.encode_bits(s.query, itq).columns == ["vec_id", "w0", "w1"]


def test_graph(spark):
    spark.sparkContext.setCheckpointDir("/tmp/twoview-test")
    v = src.emb(spark, D)
    g = G.knn_graph_exact(v, 4).cache()
    assert g.count() == 2000 and g.where("src = dst").isEmpty()
    sums = G.transitions(g, "kernel").groupBy("src").agg(F.sum("p").alias("s"))
    assert sums.where("abs(s - 1) > 1e-9").isEmpty()
    p = G.stationary(g, max_iter=15)
    assert abs(p.agg(F.sum("p")).first()[0] - 1) < 1e-9
    m = G.modes(g, p)
    assert m.where("is_mode").count() >= 1
    bad = m.where("is_mode").join(g, m.node == g.src).join(p.select(F.col("node").alias("dst"), F.col("p").alias("q")), "dst").where("q > p")
    assert bad.isEmpty() and G.mode_gallery(g, m, 2).count() == 2 * m.where("is_mode").count()
    dead = spark.createDataFrame([(1, 2, 1, 1.0), (2, 3, 1, 1.0)], "src bigint, dst bigint, rk int, dist double")
    assert abs(G.stationary(dead, symmetrize=False, max_iter=10).agg(F.sum("p")).first()[0] - 1) < 1e-9


def test_true_graph_in_blocks(spark):
    """Tiles of any size give brute force's graph, copies by id; distances are no lambdas over all pairs."""
    rng = np.random.default_rng(5)
    x = rng.normal(size=(90, 8))
    x[20:50] = x[3]
    ids = rng.permutation(90) * 3
    v = spark.createDataFrame([(int(i), r.tolist()) for i, r in zip(ids, x, strict=True)], "vec_id bigint, embedding array<double>")
    want = []
    for i, r in zip(ids, x, strict=True):
        d = ((x - r) ** 2).sum(1)
        want += [(i, j) for j in ids[[o for o in np.lexsort((ids, d)) if ids[o] != i][:4]]]
    for rows in (7, 16_384):
        g = G.knn_graph_exact(v, 4, tile_rows=rows)
        assert [(r.src, r.dst) for r in g.orderBy("src", "rk").collect()] == sorted(want, key=lambda e: e[0])
        assert "zip_with" not in plan(g) and "lambdafunction" not in plan(g)
    best = S.Nearest(ids, x, 4, exclude_self=True)
    for a in range(0, 90, 11):
        best.see(ids[a : a + 11], x[a : a + 11], rows=13, columns=5)
    assert sorted(zip(*[c.tolist() for c in best.columns()[:2]], strict=True)) == sorted(want)


def test_scans_in_blocks(spark, world):
    """Blocks over Arrow batches give the joins' results."""
    s, _, m, _ = world
    c, p = Q.encode(s.base, m).cache(), S.prepare_queries(s.query, m).cache()
    for k in (3, 500):
        assert rows(S.scan_knn(p, c, m, k)) == rows(S.adc_knn(p, c, m, k))
        assert rows(S.scan_knn(p, c, m, k, "hamming")) == rows(S.hamming_knn(p, c, m, k))
        assert rows(S.scan_knn(p, c, m, k, "mismatch")) == rows(S.mismatch_knn(p, c, m, k))
        assert rows(S.scan_knn(p, c, m, k, tau=26)) == rows(S.two_stage_knn(p, c, m, k, 26))
    assert S.scan_knn(p.limit(0), c, m, 3).isEmpty() and S.scan_knn(p, c.limit(0), m, 3).isEmpty()


def test_correlations_in_blocks(spark, world):
    """Moments of blocks are those of all pairs, equal values share a rank, and no pair becomes a row."""
    s, _, m, _ = world
    c, p = Q.encode(s.base, m), S.prepare_queries(s.query, m)
    got = {r.estimator: r for r in R.correlations(p, s.query, c, s.base, m).collect()}
    x, q = (V.collect_matrix(df)[1] for df in (s.base, s.query))
    d2 = ((q[:, None] - x[None]) ** 2).sum(2)
    own, codes = m.tables(q).reshape(len(q), 16, 16), m.encode(x)
    adc = np.stack([own[:, i, codes[:, i]] for i in range(16)]).sum(0)
    off = (m.encode(q)[:, None] != codes[None]).sum(2).astype(float)
    for name, est in (("adc", adc), ("index_mismatch", off)):
        assert abs(got[name].pearson - np.corrcoef(d2.ravel(), est.ravel())[0, 1]) < 1e-9
        assert abs(got[name].spearman - np.corrcoef(R.mid_ranks(d2).ravel(), R.mid_ranks(est).ravel())[0, 1]) < 1e-9
    assert R.mid_ranks(np.array([[2.0, 1.0, 2.0, 5.0]])).tolist() == [[1.5, 0.0, 1.5, 3.0]]
    thin = R.correlations(p, s.query, c, s.base, m, ranks=False)
    assert thin.columns == ["estimator", "pearson"] and "Window" not in plan(thin)


def test_bad_vectors_are_set_aside(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [1.0, float("nan")]), (5, [1.0, None])], "vec_id bigint, embedding array<double>")
    ok, bad = V.validate(df, 2)
    assert [r.vec_id for r in ok.collect()] == [1] and {r.vec_id: r.reason for r in bad.collect()} == {2: "null vector", 3: "wrong length", 4: "not finite", 5: "null component"}


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, world, tmp_path):
    """Bit test in the join, look-ups above it, top-k before the shuffle, no Python in between, only words read."""
    s, _, m, _ = world
    Q.encode(s.base, m, numbers=True).write.parquet(str(tmp_path / "c"))
    c, p = spark.read.parquet(str(tmp_path / "c")), S.prepare_queries(s.query, m).cache()
    p.count()
    text = plan(S.two_stage_knn(p, c, m, 5, 24))
    join = next(line for line in text.splitlines() if "BroadcastNestedLoopJoin" in line)
    assert "bit_count" in join and "WindowGroupLimit" in text
    scan = next(line for line in text.splitlines() if "FileScan parquet" in line)
    assert "codes" not in scan.split("ReadSchema")[1] and "w0" in scan
    assert "Python" not in text.split("InMemory")[0]
    one = plan(S.search_one(np.zeros(64), c, m, 5, 24))
    assert "TakeOrderedAndProject" in one and "Join" not in one


def test_storage(spark, world, tmp_path):
    from twoview.sources import storage as T

    s, _, m, _ = world
    T.save_model(spark, m, str(tmp_path / "m"))
    back = T.load_model(spark, str(tmp_path / "m"))
    assert np.array_equal(back.codebook, m.codebook) and back.spec == m.spec
    small = s.query.limit(20).cache()
    want = sorted((r.vec_id, r.embedding) for r in small.collect())
    for fmt in ("json", "csv", "orc", "text", "parquet"):
        T.export_vectors(small, str(tmp_path / fmt), fmt)
        assert sorted((r.vec_id, r.embedding) for r in T.import_vectors(spark, str(tmp_path / fmt), fmt).collect()) == want
    x = np.arange(12.0).reshape(3, 4)
    T.write_vecs(x, str(tmp_path / "v.vecs"))
    spark.dataSource.register(T.VecsSource)
    got = spark.read.format("vecs").option("path", str(tmp_path / "v.vecs")).load().orderBy("vec_id").collect()
    assert [r.embedding for r in got] == x.tolist()
    assert [r.embedding for r in T.read_vecs_files(spark, str(tmp_path / "v.vecs")).orderBy("vec_id").collect()] == x.tolist()
    codes = Q.encode(s.base, m)
    for layout in ("range", "partition"):
        T.save_codes(codes, str(tmp_path / layout), layout)
        assert spark.read.parquet(str(tmp_path / layout)).count() == codes.count()


def test_synthetic_is_stable(spark):
    a = src.synthetic(spark, 50, 4, 3, 1).orderBy("vec_id").collect()
    b = src.synthetic(spark, 50, 4, 3, 1).repartition(7).orderBy("vec_id").collect()
    assert a == b


def test_specs():
    p = I.PipelineSpec.parse("rot8_64,mi2x3,pq8")
    assert p.rotation == (8, 64) and (p.parts, p.cell_bits, p.M) == (2, 3, 8)
    with pytest.raises(ValueError):
        I.PipelineSpec.parse("mi2x3")
    with pytest.raises(ValueError):
        ModelSpec(10, 3)


def test_settled_walk_is_where_rounds_end(spark):
    """Two clusters joined by one edge mix slowly: eight rounds from even chances are not the end yet."""
    pairs = [(a + i, a + j) for a, n in ((0, 9), (100, 4)) for i in range(n) for j in range(i)] + [(0, 200), (200, 201), (201, 202), (202, 100)]
    g = spark.createDataFrame([(a, b, 1, 1.0 + (a + b) % 3) for a, b in pairs], "src long, dst long, rk int, dist double").cache()
    for weights in ("uniform", "inverse"):
        steps = {(r.src, r.dst): r.p for r in G.transitions(g, weights).collect()}
        p = {r.node: r.p for r in G.settled(g, weights).collect()}
        after = dict.fromkeys(p, 0.0)
        for (a, b), x in steps.items():
            after[b] += p[a] * x
        assert abs(sum(p.values()) - 1) < 1e-9 and all(abs(after[k] - p[k]) < 1e-12 for k in p)
    with pytest.warns(UserWarning, match="not settled"):
        early = {r.node: r.p for r in G.stationary(g, max_iter=8).collect()}
    p = {r.node: r.p for r in G.settled(g).collect()}
    assert max(abs(early[k] - p[k]) for k in p) > 1e-3


@pytest.mark.parametrize("name", ["mode_gallery", "graph_study"])
def test_mode_queries_take_the_settled_walk(spark, monkeypatch, name):
    import __spark_entry__ as entry

    monkeypatch.setattr(G, "stationary", lambda *a, **k: pytest.fail("rounds that may not have settled"))
    assert entry.queries()[name](spark, "/root/testdata/sf0.001").count() > 0


def test_dealt_search_sends_no_tables(spark):
    """Vectors travel to cells, not look-up tables: no list but the raw vector is in an exchange before cells meet."""
    s = V.split(src.emb(spark, D))
    ix = I.fit_multi_index(s.train, 64, 3, Q.train_pq(s.train, 16, 4, dims=64))
    plan = G.knn_graph(src.emb(spark, D), ix, 5, 4)._jdf.queryExecution().executedPlan().toString()
    assert "lut" not in plan and "BroadcastNestedLoopJoin" not in plan and "CartesianProduct" not in plan


def test_dealt_search_matches_the_join(spark):
    s = V.split(src.emb(spark, D))
    for residual in (False, True):
        ix = I.fit_multi_index(s.train, 64, 3, Q.train_pq(s.train, 16, 4, dims=64), residual=residual)
        coded = I.encode_cells(s.base, ix)
        want = I.search_ivf(I.probe_cells(s.query, ix, 9), coded, ix, 6, 30)
        assert rows(I.search_ivf_dealt(s.query, coded, ix, 6, 9, 30, code_rows=4, query_rows=3)) == rows(want)


def test_exact_ties_go_to_the_smaller_id(spark):
    v = spark.createDataFrame([(i, [float(i % 3), 1.0]) for i in range(60)], "vec_id long, embedding array<double>").repartition(3)
    got = S.exact_knn(v.where("vec_id = 0"), v, 25).orderBy("rk").collect()
    assert [r.vec_id for r in got] == [*range(0, 60, 3), *range(1, 15, 3)]
    own = S.exact_knn(v, v, 2, exclude_self=True).collect()
    assert all(r.vec_id != r.qid for r in own) and len(own) == 120


def test_samples_go_by_hash(spark):
    v = spark.range(5000).selectExpr("id AS vec_id", "array(double(id), 1.0) AS embedding")
    ids, x = V.collect_matrix(v, 500)
    assert len(ids) == 500 and ids.max() > 4000 and (np.diff(ids) > 0).all() and (x[:, 0] == ids).all()


def test_descent_measures_pairs_in_blocks(spark):
    """Neighbours of neighbours as brute force has them, hubs in parts or whole; pairs never become rows with both vectors."""
    rng = np.random.default_rng(12)
    x = rng.normal(size=(70, 6))
    x[30:40] = x[2]
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id bigint, embedding array<double>")
    edges = {(i, int(j)) for i in range(70) for j in [*rng.choice(70, 3), 5] if i != j}
    g = spark.createDataFrame([(*e, 1, 0.0) for e in edges], "src bigint, dst bigint, rk int, dist double")
    both = edges | {(b, a) for a, b in edges}
    pairs = edges | {(a, c) for a, b in both for d, c in both if b == d and a != c}
    want = []
    for i in range(70):
        ids = np.array(sorted(c for a, c in pairs if a == i))
        d = ((x[ids] - x[i]) ** 2).sum(1).round(9)
        want += [(i, int(j), float(e)) for j, e in list(zip(ids[np.lexsort((ids, d))], np.sort(d), strict=True))[:4]]
    for hub in (5, 1024):
        out = G.graph_descent(g, v, 4, hub=hub)
        assert [(r.src, r.dst, round(r.dist, 9)) for r in out.orderBy("src", "rk").collect()] == want
    assert "MapInArrow" in plan(out)


def test_graph_study_refines_once(spark, monkeypatch):
    import __spark_entry__ as entry

    frame = type(spark.range(1))
    made, kept, descent, cache = [], [], G.graph_descent, frame.cache
    monkeypatch.setattr(G, "graph_descent", lambda *a, **k: made.append(descent(*a, **k)) or made[-1])
    monkeypatch.setattr(frame, "cache", lambda self: kept.append(self) or cache(self))
    entry.queries()["graph_study"](spark, "/root/testdata/sf0.001")
    assert len(made) == 1 and any(k is made[0] for k in kept)


def test_scans_send_the_smaller_side(spark, world, monkeypatch):
    """Tables of many queries stay in their tasks: codes are sent to them, in chunks; few queries are sent to the codes. Results are the joins'."""
    s, _, m, _ = world
    c, p = Q.encode(s.base, m).cache(), S.prepare_queries(s.query, m).cache()
    sent, broadcast = [], type(spark.sparkContext).broadcast
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", lambda self, v: sent.append(v) or broadcast(self, v))
    monkeypatch.setattr(S, "BROADCAST_BYTES", 3000)
    S.scan_knn(p, c, m, 4)
    assert len(sent) > 1 and sum(len(v[0]) for v in sent) == c.count() and all(v[1].shape[1] == m.spec.n_words for v in sent)
    sent.clear()
    few = p.where("qid < 20")
    assert S.scan_knn(few, c, m, 4).count() == 8 and sum(t.num_rows for t in sent) == 2
    for asked in (p, few):
        assert rows(S.scan_knn(asked, c, m, 4)) == rows(S.adc_knn(asked, c, m, 4))
        assert rows(S.scan_knn(asked, c, m, 4, "hamming")) == rows(S.hamming_knn(asked, c, m, 4))
        assert rows(S.scan_knn(asked, c, m, 4, tau=24)) == rows(S.two_stage_knn(asked, c, m, 4, 24))


def test_codes_seen_in_any_order(spark):
    """Blocks of any size and order give brute force's lists, ties by id, for numbers of any bits."""
    rng = np.random.default_rng(7)
    for M, b in ((16, 8), (12, 5), (40, 8)):
        spec = ModelSpec(M, M, b)
        numbers, own = rng.integers(0, 4, (300, M)), rng.integers(0, 4, (6, M))
        numbers[50:150] = numbers[7]
        ids, words, asked = rng.permutation(300) * 2, pack_words(numbers, spec), pack_words(own, spec)
        lut = rng.integers(0, 9, (6, M * spec.K)).astype(float)
        bits = np.bitwise_count(numbers[None] ^ own[:, None]).sum(2)
        sums = np.stack([lut[:, m * spec.K + numbers[:, m]] for m in range(M)]).sum(0)
        for by, tau, want in (("hamming", None, bits), ("mismatch", None, (numbers[None] != own[:, None]).sum(2)), ("adc", None, sums), ("adc", M - 1, np.where(bits < M, sums, np.inf))):
            for order in (np.argsort(ids), np.arange(300)):
                best = S.Scanned(np.arange(6), asked, lut, spec, 20, by, tau)
                for a in range(0, 300, 90):
                    best.see(ids[order[a : a + 90]], words[order[a : a + 90]], rows=40)
                got = best.batch().to_pylist()
                for j in range(6):
                    near = [i for i in np.lexsort((ids, want[j])) if np.isfinite(want[j][i])][:20]
                    assert [(r["vec_id"], r["score"]) for r in got if r["qid"] == j] == [(ids[i], want[j][i]) for i in near]


def test_histogram_of_blocks():
    rng = np.random.default_rng(1)
    for bits, n in ((128, 301), (128, 20), (320, 301)):
        x, y = (rng.integers(0, 2, (rows, bits)) for rows in (n, 303))
        a, b = (pack_words(v, ModelSpec(bits, bits, 1)).view(np.uint64) for v in (x, y))
        want = np.bincount((x[:, None] != y[None]).sum(2).ravel(), minlength=bits + 1)
        assert C.histogram([np.ascontiguousarray(w) for w in a.T], b, bits).tolist() == want.tolist()


def test_nearest_centroids_in_blocks():
    rng = np.random.default_rng(2)
    x, c = rng.normal(size=(100, 4)), rng.normal(size=(9, 4))
    d = ((x[:, None] - c[None]) ** 2).sum(2)
    near, least = Q._nearest(x, c, rows=33)
    assert near.tolist() == d.argmin(1).tolist() and np.allclose(least + (x * x).sum(1), d.min(1))


def test_ablation_keeps_no_tables(spark, monkeypatch):
    """Look-up tables, M * K numbers a query, are neither kept nor dealt out; the true neighbours are sent to the lists."""
    from twoview.plans import experiments as X

    frame, kept, asked = type(spark.range(1)), [], []
    cache, recall = frame.cache, R.recall_at
    monkeypatch.setattr(frame, "cache", lambda self: kept.append(self.columns) or cache(self))
    monkeypatch.setattr(R, "recall_at", lambda got, truth: asked.append(plan(got)) or recall(got, truth))
    X.ablation_grid(V.split(src.emb(spark, D)), 64, 16, 4, constructions=("plain",), seeds=(1,))
    assert kept and not any("lut" in columns for columns in kept)
    assert len(asked) == 6 and all("BroadcastHashJoin" in text for text in asked)


def test_words_are_counted_where_texts_are(spark, tmp_path, monkeypatch):
    """The bags that plain expressions give, of odd texts and repeated ids, with one exchange and no row a word."""
    texts = [(1, ""), (2, "  a  B "), (3, None), (4, "É a\tb a"), (1, "a a"), (None, "x y"), (None, "y z"), (6, "a" * 10 + " " + "b " * 3000), (7, " ")]
    spark.createDataFrame(texts, "doc_id bigint, text string").write.parquet(str(tmp_path / "documents.parquet"))
    w = spark.createDataFrame(texts, "vec_id bigint, text string").select("vec_id", F.explode(F.split(F.lower("text"), " ")).alias("w"))
    h = F.md5("w")
    signs = w.select("vec_id", (F.conv(F.substring(h, 1, 4), 16, 10).cast("int") % 64).alias("d"), F.when(F.substring(h, 5, 1) >= "8", -1.0).otherwise(1.0).alias("s"))
    want = {}
    for r in signs.groupBy("vec_id", "d").agg(F.sum("s").alias("v")).collect():
        want.setdefault(r.vec_id, np.zeros(64))[r.d] = r.v
    for piece in (4 << 20, 5):
        monkeypatch.setattr(src, "PIECE", piece)
        df = src.words(spark, str(tmp_path))
        got = {r.vec_id: r.embedding for r in df.collect()}
        assert got.keys() == want.keys() and all(got[k] == (v / max(np.sqrt(v @ v), 1e-300)).tolist() for k, v in want.items())
    text = plan(src.words(spark, str(tmp_path)))
    assert "Generate" not in text and text.count("Exchange") == 1
