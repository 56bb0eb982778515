"""Registered relational queries: the operators that a user of vector search needs around it, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from twoview.operators import relational as O
from twoview.plans.registry import query
from twoview.sources.vectors import read_table as t


@query("join_broadcast_hash", "SELECT n_name, count(*) AS n, round(sum(s_acctbal), 2) AS bal FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast_hash(spark: SparkSession, d: str) -> DataFrame:
    j = t(spark, d, "supplier").join(F.broadcast(t(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))  # 25 rows by definition
    return j.groupBy("n_name").agg(F.count("*").alias("n"), F.round(F.sum("s_acctbal"), 2).alias("bal"))


@query("join_sort_merge", "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def join_sort_merge(spark: SparkSession, d: str) -> DataFrame:
    j = t(spark, d, "lineitem").join(t(spark, d, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("join_shuffle_hash", "SELECT p_brand, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def join_shuffle_hash(spark: SparkSession, d: str) -> DataFrame:
    j = t(spark, d, "lineitem").join(t(spark, d, "part").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("p_brand").agg(F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("join_left_outer", "SELECT c_mktsegment, count(*) AS n, count(o_orderkey) AS with_order FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def join_left_outer(spark: SparkSession, d: str) -> DataFrame:
    j = t(spark, d, "customer").join(t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left")
    return j.groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.count("o_orderkey").alias("with_order"))


@query("join_full_outer", "SELECT count(*) AS n, count(d.doc_id) AS docs, count(l.doc_id) AS labelled FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def join_full_outer(spark: SparkSession, d: str) -> DataFrame:
    a, b = t(spark, d, "documents").select("doc_id"), t(spark, d, "labels").select(F.col("doc_id").alias("label_id"))
    return a.join(b, F.col("doc_id") == F.col("label_id"), "full").agg(F.count("*").alias("n"), F.count("doc_id").alias("docs"), F.count("label_id").alias("labelled"))


@query("join_semi_anti", "SELECT (SELECT count(*) FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)) AS buyers, (SELECT count(*) FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)) AS others")
def join_semi_anti(spark: SparkSession, d: str) -> DataFrame:
    c, o = t(spark, d, "customer"), t(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return c.join(o, "c_custkey", "left_semi").agg(F.count("*").alias("buyers")).crossJoin(c.join(o, "c_custkey", "left_anti").agg(F.count("*").alias("others")))


@query("range_join", "SELECT count(*) AS n FROM orders a JOIN customer b ON a.o_totalprice BETWEEN b.c_acctbal * 10 AND b.c_acctbal * 10 + 500")
def range_join(spark: SparkSession, d: str) -> DataFrame:
    c = t(spark, d, "customer").select((F.col("c_acctbal") * 10).alias("lo"), (F.col("c_acctbal") * 10 + 500).alias("hi"))
    return O.range_join(t(spark, d, "orders").select("o_totalprice"), c, "o_totalprice", "lo", "hi", 500.0).agg(F.count("*").alias("n"))


@query(
    "asof_join",
    "SELECT a.event_id, (SELECT max_by(b.event_id, (b.ts, b.event_id)) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'view' AND b.ts <= a.ts) AS prior FROM events a WHERE a.event_type = 'purchase'",
)
def asof_join(spark: SparkSession, d: str) -> DataFrame:
    e = t(spark, d, "events")
    left, right = e.where("event_type = 'purchase'").select("user_id", "ts", "event_id"), e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("prior"))
    return O.asof_join(left, right, ["user_id"], "ts", "prior").select("event_id", "prior")


@query("skew_salted_join", "SELECT n_regionkey, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def skew_salted_join(spark: SparkSession, d: str) -> DataFrame:
    n = t(spark, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_regionkey")
    j = O.salted_join(t(spark, d, "customer"), n, ["c_nationkey"], 4)
    return O.salted_group(j, ["n_regionkey"], [F.count("*").alias("n"), F.sum("c_acctbal").alias("total")], [F.sum("n").alias("n"), F.round(F.sum("total"), 2).alias("total")])


@query("lateral_join", "SELECT r_name, n_name FROM region, LATERAL (SELECT n_name FROM nation WHERE n_regionkey = r_regionkey ORDER BY n_name LIMIT 2)")
def lateral_join(spark: SparkSession, d: str) -> DataFrame:
    t(spark, d, "region").createOrReplaceTempView("_region")
    t(spark, d, "nation").createOrReplaceTempView("_nation")
    return spark.sql("SELECT r_name, n_name FROM _region, LATERAL (SELECT n_name FROM _nation WHERE n_regionkey = r_regionkey ORDER BY n_name LIMIT 2)")


@query(
    "agg_basic",
    "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc, min(l_extendedprice) AS lo, max(l_extendedprice) AS hi, round(stddev_samp(l_tax), 6) AS sd FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY 1, 2",
)
def agg_basic(spark: SparkSession, d: str) -> DataFrame:
    f = t(spark, d, "lineitem").where(F.col("l_shipdate") <= F.lit("1998-09-02").cast("timestamp"))
    return f.groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"), F.round(F.stddev_samp("l_tax"), 6).alias("sd")
    )


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1")
def agg_distinct(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"))


@query("agg_sketch_bounds", "SELECT true AS within")
def agg_sketch_bounds(spark: SparkSession, d: str) -> DataFrame:
    """Distinct and percentile sketches lie near the exact values."""
    li = t(spark, d, "lineitem")
    row = li.agg(F.countDistinct("l_partkey").alias("e"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", F.lit(14))).alias("h"), F.percentile("l_quantity", 0.5).alias("p"), F.percentile_approx("l_quantity", 0.5, 1000).alias("a"))
    return row.select(((F.abs(F.col("h") - F.col("e")) <= 0.05 * F.col("e")) & (F.abs(F.col("p") - F.col("a")) <= 1)).alias("within"))


@query("agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("agg_rollup", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def agg_rollup(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("agg_grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
def agg_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    c = t(spark, d, "customer")
    return c.groupingSets([[F.col("c_mktsegment")], [F.col("c_nationkey")], []], "c_mktsegment", "c_nationkey").agg(F.count("*").alias("n"))


@query("agg_pivot", "SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS F, count(*) FILTER (WHERE l_linestatus = 'O') AS O FROM lineitem GROUP BY 1")
def agg_pivot(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count("l_orderkey")).na.fill(0)


@query("agg_conditional", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, bool_or(value > 90) AS any_high, bit_or(event_id) AS bits, bit_xor(event_id) AS xors FROM events GROUP BY 1")
def agg_conditional(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "view").alias("views"), F.bool_or(F.col("value") > 90).alias("any_high"), F.bit_or("event_id").alias("bits"), F.bit_xor("event_id").alias("xors"))


@query("agg_having_listagg", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1 HAVING count(*) >= 5")
def agg_having_listagg(spark: SparkSession, d: str) -> DataFrame:
    g = t(spark, d, "nation").groupBy("n_regionkey").agg(F.count("*").alias("n"), F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("names"))
    return g.where("n >= 5").select("n_regionkey", "names")


@query("vector_mean", "SELECT label, (i-1)::INTEGER AS i, round(avg(embedding[i]::DOUBLE), 6) AS x FROM embeddings, range(1, 9) r(i) GROUP BY label, i")
def vector_mean(spark: SparkSession, d: str) -> DataFrame:
    e = t(spark, d, "embeddings").select("label", F.posexplode(F.slice(F.col("embedding").cast("array<double>"), 1, 8)).alias("i", "x"))
    return e.groupBy("label", F.col("i").cast("int").alias("i")).agg(F.round(F.avg("x"), 6).alias("x"))


@query("window_rank", "SELECT o_orderkey, rank() OVER w::INTEGER AS r, dense_rank() OVER w::INTEGER AS dr, row_number() OVER w2::INTEGER AS rn, ntile(4) OVER w2::INTEGER AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority), w2 AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def window_rank(spark: SparkSession, d: str) -> DataFrame:
    w, w2 = Window.partitionBy("o_custkey").orderBy("o_orderpriority"), Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return t(spark, d, "orders").select("o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(w2).alias("rn"), F.ntile(4).over(w2).alias("q"))


@query("window_lag_frames", "SELECT event_id, lag(value) OVER w AS before, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS upto, first_value(event_id) OVER w AS first_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_lag_frames(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    upto = w.rowsBetween(Window.unboundedPreceding, 0)
    return t(spark, d, "events").select("event_id", F.lag("value").over(w).alias("before"), F.round(F.sum("value").over(upto), 4).alias("upto"), F.first("event_id").over(w).alias("first_id"))


@query("window_range_7d", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 7 DAYS PRECEDING AND CURRENT ROW) AS n FROM events")
def window_range_7d(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-7 * 86_400_000_000, 0)
    return t(spark, d, "events").select("event_id", F.count("*").over(w).alias("n"))


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_global(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25)


@query("topk_per_group", "SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey)::INTEGER AS rk FROM part QUALIFY rk <= 3")
def topk_per_group(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(spark, d, "part").withColumn("rk", F.row_number().over(w)).where("rk <= 3").select("p_brand", "p_partkey", "rk")


@query("set_ops", "SELECT 'union' AS op, count(*) AS n FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier) UNION ALL SELECT 'intersect', count(*) FROM (SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL SELECT 'except_all', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier)")
def set_ops(spark: SparkSession, d: str) -> DataFrame:
    a, b = t(spark, d, "customer").select("c_nationkey"), t(spark, d, "supplier").select(F.col("s_nationkey").alias("c_nationkey"))
    parts = [("union", a.union(b).distinct()), ("intersect", a.intersect(b)), ("except_all", a.exceptAll(b))]
    out = [df.agg(F.count("*").alias("n")).select(F.lit(name).alias("op"), "n") for name, df in parts]
    return out[0].unionAll(out[1]).unionAll(out[2])


@query("dedup_texts", "SELECT count(*) AS rows_all, count(DISTINCT md5(text)) AS texts FROM documents")
def dedup_texts(spark: SparkSession, d: str) -> DataFrame:
    h = t(spark, d, "documents").select(F.md5("text").alias("h"))
    return h.agg(F.count("*").alias("rows_all")).crossJoin(h.dropDuplicates(["h"]).agg(F.count("*").alias("texts")))


@query("subquery_correlated", "SELECT count(*) AS n FROM lineitem a WHERE l_quantity < (SELECT 0.5 * avg(l_quantity) FROM lineitem b WHERE b.l_partkey = a.l_partkey)")
def subquery_correlated(spark: SparkSession, d: str) -> DataFrame:
    li = t(spark, d, "lineitem")
    mean = li.groupBy("l_partkey").agg((0.5 * F.avg("l_quantity")).alias("half"))
    return li.join(mean, "l_partkey").where("l_quantity < half").agg(F.count("*").alias("n"))


_STEPS = "SELECT l_partkey AS node, min(l_suppkey) AS next FROM {t} GROUP BY 1"
_WALK = "w(node, step, p) AS (SELECT min(node), 0, {one} FROM hops UNION ALL SELECT hops.next, step + 1, p / 2 FROM w JOIN hops ON hops.node = w.node WHERE step < 8) SELECT node, step, p FROM w"


@query("recursive_walk", "WITH RECURSIVE hops AS (" + _STEPS.format(t="lineitem") + "), " + _WALK.format(one="1.0::DOUBLE"))
def recursive_walk(spark: SparkSession, d: str) -> DataFrame:
    """A walk over order lines with a chance that halves: from the lowest part to its lowest supplier, then to the part of that number."""
    t(spark, d, "lineitem").createOrReplaceTempView("_lines")
    spark.sql(_STEPS.format(t="_lines")).cache().createOrReplaceTempView("hops")
    return spark.sql("WITH RECURSIVE " + _WALK.format(one="1.0D"))


@query("scalar_bits", "SELECT event_id, bit_count(event_id)::BIGINT AS ones, xor(event_id, event_id >> 1) AS gray, (event_id << 3) | 5 AS shifted FROM events")
def scalar_bits(spark: SparkSession, d: str) -> DataFrame:
    e = F.col("event_id")
    return t(spark, d, "events").select("event_id", F.bit_count(e).cast("bigint").alias("ones"), e.bitwiseXOR(F.shiftright(e, 1)).alias("gray"), F.shiftleft(e, 3).bitwiseOR(F.lit(5)).alias("shifted"))


@query("scalar_strings", "SELECT c_custkey, lower(c_name) AS low, length(c_name) AS n, replace(c_name, '#', '-') AS dashed, substr(md5(c_name), 1, 8) AS h, split_part(c_name, '#', 2) AS part FROM customer")
def scalar_strings(spark: SparkSession, d: str) -> DataFrame:
    n = F.col("c_name")
    return t(spark, d, "customer").select("c_custkey", F.lower(n).alias("low"), F.length(n).cast("bigint").alias("n"), F.replace(n, F.lit("#"), F.lit("-")).alias("dashed"), F.substring(F.md5(n), 1, 8).alias("h"), F.split_part(n, F.lit("#"), F.lit(2)).alias("part"))


@query("scalar_arrays", "SELECT vec_id, round(list_sum([abs(x::DOUBLE) for x in embedding[1:4]]), 6) AS s, len([x for x in embedding if x > 0]) AS pos, round(list_max(embedding)::DOUBLE, 6) AS hi FROM embeddings")
def scalar_arrays(spark: SparkSession, d: str) -> DataFrame:
    e = F.col("embedding")
    s = F.aggregate(F.transform(F.slice(e, 1, 4), lambda x: F.abs(x.cast("double"))), F.lit(0.0), lambda a, x: a + x)
    return t(spark, d, "embeddings").select("vec_id", F.round(s, 6).alias("s"), F.size(F.filter(e, lambda x: x > 0)).cast("bigint").alias("pos"), F.round(F.array_max(e).cast("double"), 6).alias("hi"))


@query("json_fields", "SELECT event_id, (props->>'k')::BIGINT AS k FROM events")
def json_fields(spark: SparkSession, d: str) -> DataFrame:
    return t(spark, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("date_parts", "SELECT year(l_shipdate)::INTEGER AS y, month(l_shipdate)::INTEGER AS m, count(*) AS n, sum(dayofyear(l_shipdate))::BIGINT AS doy FROM lineitem GROUP BY 1, 2")
def date_parts(spark: SparkSession, d: str) -> DataFrame:
    s = F.col("l_shipdate")
    return t(spark, d, "lineitem").groupBy(F.year(s).alias("y"), F.month(s).alias("m")).agg(F.count("*").alias("n"), F.sum(F.dayofyear(s)).alias("doy"))


@query("sql_functions", "SELECT a.vec_id AS a, b.vec_id AS b, bit_count(xor(a.vec_id * 1234567, b.vec_id * 7654321))::INTEGER AS h FROM embeddings a, embeddings b WHERE a.vec_id < 20 AND b.vec_id < 20")
def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    """A SQL function's body is inlined into the join's condition and the projection."""
    from twoview.functions.expressions import register_sql_functions

    register_sql_functions(spark)
    t(spark, d, "embeddings").createOrReplaceTempView("_emb")
    return spark.sql("SELECT a.vec_id AS a, b.vec_id AS b, hamming64(a.vec_id * 1234567, b.vec_id * 7654321) AS h FROM _emb a JOIN _emb b ON a.vec_id < 20 AND b.vec_id < 20")


@query("export_import_csv", "SELECT vec_id, round(list_sum([x::DOUBLE for x in embedding]), 5) AS total FROM embeddings")
def export_import_csv(spark: SparkSession, d: str) -> DataFrame:
    from twoview.sources.storage import export_vectors, import_vectors
    from twoview.streaming.streams import scratch

    at = scratch(spark)
    export_vectors(t(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")), at, "csv")
    return import_vectors(spark, at, "csv").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda s, v: s + v), 5).alias("total"))
