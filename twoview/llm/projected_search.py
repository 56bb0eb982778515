"""Largest inner products by low-dimensional stable projections, kd-trees and a chi-square stopping test.

A vector gets one more component so that all have equal length; the largest inner product with a query is then
the smallest distance. Gaussian projections to a few dimensions keep distances up to a chi-square factor: at
distance d the squared projected distance is d**2 times a chi-square variable. Space is cut into kd-cells of the
projections, and each cell's blocks hold a kd-tree of leaves. Leaves are verified in ascending projected distance
until the test holds: were there a nearer neighbour than the present k-th, it would lie nearer in projection
with the probability asked for. A query first looks in its own cell, which gives the distance to test with,
then only in cells that the test leaves.

Splits come from a bounded sample (max_sample rows, by a hash of all ids); every vector is indexed. A cell's rows
are dealt to blocks of bounded size, and queries of like cells to blocks of their own; vectors go to those blocks of queries alone
that one of the block's queries asks their cell for. Equal vectors of a block are kept once, with as
many of their smallest ids as a query can take.

Cases: vectors that are null, zero, without id, of another length than most, or hold null or non-finite components
take no part, as queries or as candidates. Equal scores go to the smaller vec_id. Rows of equal vec_id: each counts
as a candidate, none for its own id; the query is answered once a row. Fewer than k candidates: all are returned.
An empty table gives an empty result. Other columns are left out of account.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from twoview.llm.base import written

OUT = "query_id bigint, query_row bigint, vec_id bigint, score double"


def chi_square_cdf(x: np.ndarray, dims: int) -> np.ndarray:
    """Distribution function of the chi-square law for an even number of dimensions."""
    half = np.asarray(x, float) / 2
    term, total = np.ones_like(half), np.ones_like(half)
    for i in range(1, dims // 2):
        term = term * half / i
        total = total + term
    return 1 - np.exp(-np.minimum(half, 700)) * total


def kd_splits(points: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Dimension and value of the splits of a complete kd-tree, in heap order: widest dimension, median."""
    dims, values = np.zeros(max(2**depth - 1, 0), np.int64), np.zeros(max(2**depth - 1, 0))
    parts = {0: points}
    for node in range(2**depth - 1):
        part = parts.pop(node)
        if len(part):
            d = int(np.argmax(part.max(0) - part.min(0)))
            dims[node], values[node] = d, np.median(part[:, d])
        high = part[:, dims[node]] >= values[node]
        parts[2 * node + 1], parts[2 * node + 2] = part[~high], part[high]
    return dims, values


def kd_cells(points: np.ndarray, splits: tuple[np.ndarray, np.ndarray], depth: int) -> np.ndarray:
    """The leaf, from 0, that each point falls into."""
    node = np.zeros(len(points), np.int64)
    for _ in range(depth):
        node = 2 * node + 1 + (points[np.arange(len(points)), splits[0][node]] >= splits[1][node])
    return node - (2**depth - 1)


def box_distances(points: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Squared distances from points to boxes, one row a point."""
    out = np.zeros((len(points), len(low)))
    for d in range(points.shape[1]):
        x = points[:, d, None]
        out += np.maximum(np.maximum(low[None, :, d] - x, x - high[None, :, d]), 0) ** 2
    return out


def _matrix(column: pa.ChunkedArray | pa.Array, width: int) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    off = column.offsets.to_numpy()
    return column.values.to_numpy()[off[0] : off[-1]].reshape(-1, width)


def _unique(ids: np.ndarray, x: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct vectors, and of each the most smallest ids as (ids, which vector)."""
    x = np.ascontiguousarray(x + 0.0)
    _, first, which = np.unique(x.view([("", f"V{x.shape[1] * 8}")]).ravel(), return_index=True, return_inverse=True)
    order = np.lexsort((ids, which.ravel()))
    ids, which = ids[order], which.ravel()[order]
    nth = np.arange(len(ids)) - np.searchsorted(which, which)
    return x[first], ids[nth < most], which[nth < most]


def search_block(ids: np.ndarray, x: np.ndarray, qids: np.ndarray, q: np.ndarray, qp: np.ndarray, bound: np.ndarray, *, gauss: np.ndarray, k: int, length2: float, sure: float, leaf: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best of a block for each query, of those that reach its bound: query's place, id, score.

    ids, x: the block's ids and vectors; q, qp: the queries and their projections; bound: an inner product that the
    k-th best is known to reach.
    """
    x, ids, which = _unique(ids, x, k + 1)
    proj = x @ gauss[:-1] + np.sqrt(np.maximum(length2 - (x * x).sum(1), 0))[:, None] * gauss[-1]
    depth = max(0, int(np.ceil(np.log2(max(len(x), 1) / leaf))))
    cell = kd_cells(proj, kd_splits(proj, depth), depth)
    order = np.argsort(cell, kind="stable")
    cuts = np.searchsorted(cell[order], np.arange(2**depth + 1))
    full = np.flatnonzero(np.diff(cuts))
    low = np.stack([proj[order[cuts[i] : cuts[i + 1]]].min(0) for i in full])
    high = np.stack([proj[order[cuts[i] : cuts[i + 1]]].max(0) for i in full])
    far = box_distances(qp, low, high)
    near = np.argsort(far, axis=1, kind="stable")
    owners = np.split(np.arange(len(ids)), np.searchsorted(which, np.arange(1, len(x))))
    q2 = (q * q).sum(1)
    slack = 1e-9 * np.sqrt(q2 * length2) + 1e-300
    floor = bound.copy()
    going = np.ones(len(q), bool)
    kept: list[list[tuple[np.ndarray, np.ndarray]]] = [[] for _ in range(len(q))]
    n_kept = np.zeros(len(q), np.int64)
    for r in range(len(full)):
        at = near[:, r]
        reach = np.maximum(q2 + length2 - 2 * floor, 1e-300)
        with np.errstate(over="ignore", invalid="ignore"):
            going &= ~(chi_square_cdf(far[np.arange(len(q)), at] / reach, qp.shape[1]) >= sure) | ~np.isfinite(floor)
        if not going.any():
            break
        for i in np.unique(at[going]):
            rows = order[cuts[full[i]] : cuts[full[i] + 1]]
            who = np.flatnonzero(going & (at == i))
            s = q[who] @ x[rows].T
            hit = s >= (floor - slack)[who, None]
            for j in np.flatnonzero(hit.any(1)).tolist():
                w = who[j]
                mine = rows[hit[j]]
                kept[w].append((mine, s[j][hit[j]]))
                n_kept[w] += len(mine)
                if n_kept[w] > k:
                    v, t = (np.concatenate(z) for z in zip(*kept[w], strict=True))
                    cut = np.partition(t, len(t) - k - 1)[len(t) - k - 1]  # one more than k, as one may be the query itself
                    floor[w] = max(floor[w], cut)
                    use = t >= cut - slack[w]
                    kept[w], n_kept[w] = [(v[use], t[use])], int(use.sum())
    out_q, out_i, out_s = [], [], []
    for w in np.flatnonzero(n_kept).tolist():
        v = np.concatenate([z[0] for z in kept[w]])
        exact = (x[v] * q[w]).sum(1)  # summed alike for equal vectors, so that ties are ties
        n = np.array([len(owners[i]) for i in v])
        got, s = np.concatenate([ids[owners[i]] for i in v]), np.repeat(exact, n)
        other = got != qids[w]
        got, s = got[other], s[other]
        best = np.lexsort((got, -s))[:k]
        out_q.append(np.full(len(best), w))
        out_i.append(got[best])
        out_s.append(s[best])
    if not out_q:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    return np.concatenate(out_q), np.concatenate(out_i), np.concatenate(out_s)


def projected_search(vectors: DataFrame, is_query: Column, *, k: int = 20, dims: int = 8, sure: float = 0.98, cell_rows: int = 8192, leaf: int = 512, max_sample: int = 50_000, query_rows: int = 4096, seed: int = 11) -> DataFrame:
    """The k largest inner products (query_id, rank, vec_id, score) of the rows that is_query marks, among all rows but their own.

    vectors: vec_id, embedding; dims must be even.
    """
    spark = vectors.sparkSession
    emb = F.col("embedding")
    usable = (
        vectors.withColumn("_q", F.coalesce(is_query, F.lit(False)))
        .select("vec_id", emb.cast("array<double>").alias("x"), "_q")
        .where(F.col("vec_id").isNotNull() & F.col("x").isNotNull())
        .where(~F.exists("x", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf"))) & F.exists("x", lambda v: v != 0))
    )
    norm2 = F.aggregate("x", F.lit(0.0), lambda a, v: a + v * v)
    sizes = usable.groupBy(F.size("x").alias("width")).agg(F.count("*").alias("n"), F.max(norm2).alias("length2"), F.count_if("_q").alias("queries")).collect()
    empty = spark.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    if not sizes:
        return empty
    top = max(sizes, key=lambda r: (r.n, r.width))
    width, n, length2 = top.width, top.n, float(top.length2)
    usable = usable.where(F.size("x") == width)
    gauss = np.random.default_rng(seed).normal(size=(width + 1, dims))
    depth = int(np.clip(np.ceil(np.log2(max(n, 1) / cell_rows)), 0, 12))
    share = min(1.0, 1.5 * max_sample / max(n, 1))
    picked = usable.where(F.pmod(F.xxhash64("vec_id"), F.lit(1 << 20)) <= int(share * (1 << 20))).select("x", F.xxhash64("vec_id").alias("h")).orderBy("h").limit(max_sample).toArrow()

    def project(x: np.ndarray, query: bool) -> np.ndarray:
        extra = 0.0 if query else np.sqrt(np.maximum(length2 - (x * x).sum(1), 0))[:, None] * gauss[-1]
        return x @ gauss[:-1] + extra

    splits = kd_splits(project(_matrix(picked["x"], width), False) if len(picked) else np.zeros((0, dims)), depth)

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x = _matrix(batch.column(1), width)
                own, asked = project(x, False), project(x, True)
                cols = [kd_cells(own, splits, depth), kd_cells(asked, splits, depth)]
                lists = [pa.FixedSizeListArray.from_arrays(pa.array(v.ravel()), dims).cast(pa.list_(pa.float64())) for v in (own, asked)]
                yield pa.RecordBatch.from_arrays([*batch.columns, *map(pa.array, cols), *lists], names=["vec_id", "x", "_q", "cell", "q_cell", "own", "asked"])

    placed = written(
        usable.mapInArrow(assign, "vec_id bigint, x array<double>, _q boolean, cell bigint, q_cell bigint, own array<double>, asked array<double>").withColumn(
            "row", F.monotonically_increasing_id()
        ),
        "projected",
    )
    stats = placed.groupBy("cell").agg(
        F.count("*").alias("n"), *[F.min(F.col("own")[d]).alias(f"l{d}") for d in range(dims)], *[F.max(F.col("own")[d]).alias(f"h{d}") for d in range(dims)]
    ).collect()  # one row a cell, 4096 at most
    cells = np.array([r.cell for r in stats])
    low = np.array([[r[f"l{d}"] for d in range(dims)] for r in stats])
    high = np.array([[r[f"h{d}"] for d in range(dims)] for r in stats])
    blocks = {r.cell: -(-r.n // cell_rows) for r in stats}
    n_blocks = F.create_map(*[v for c, b in blocks.items() for v in (F.lit(c), F.lit(b))])
    per_cell = {r.q_cell: r.n for r in placed.where("_q").groupBy("q_cell").agg(F.count("*").alias("n")).collect()}  # one row a cell, 4096 at most
    first, many, blocks_used, room = {}, {}, 0, 0
    for c, n_own in sorted(per_cell.items()):  # cells that follow each other lie close in the tree
        if n_own > room:
            first[c], many[c] = blocks_used, -(-n_own // query_rows)
            blocks_used += many[c]
            room = query_rows - n_own if many[c] == 1 else 0
        else:
            first[c], many[c] = blocks_used - 1, 1
            room -= n_own
    where = ["cell", "block", "q_block"]
    none = F.create_map(F.lit(0).cast("bigint"), F.lit(0))
    begin, parts = (F.create_map(*[v for c in table for v in (F.lit(c), F.lit(table[c]))]) if table else none for table in (first, many))
    q_block = (begin[F.col("q_cell")] + F.pmod(F.xxhash64("row"), parts[F.col("q_cell")])).cast("int")
    data = placed.select("cell", "vec_id", "x", F.pmod(F.xxhash64("vec_id", "row"), n_blocks[F.col("cell")]).alias("block"))
    queries = placed.where("_q").select(F.col("row").alias("query_row"), F.col("vec_id").alias("query_id"), F.col("x").alias("q"), "asked", "q_cell", q_block.alias("q_block"))

    def search(left: pa.Table, right: pa.Table) -> pa.Table:
        names = [c.split()[0] for c in OUT.split(", ")]
        if not left.num_rows or not right.num_rows:
            return pa.table({c: pa.array([], pa.float64() if c == "score" else pa.int64()) for c in names})
        qids, rows = left["query_id"].to_numpy(), left["query_row"].to_numpy()
        w, got, s = search_block(
            right["vec_id"].to_numpy(), _matrix(right["x"], width), qids, _matrix(left["q"], width), _matrix(left["asked"], dims), left["bound"].to_numpy(), gauss=gauss, k=k, length2=length2, sure=sure, leaf=leaf
        )
        return pa.table({"query_id": qids[w], "query_row": rows[w], "vec_id": got, "score": s})

    def run(asked: DataFrame) -> DataFrame:
        spread = asked.withColumn("block", F.explode(F.sequence(F.lit(0).cast("bigint"), n_blocks[F.col("cell")].cast("bigint") - 1)))
        wanted = asked.select(F.col("cell").alias("_cell"), F.col("q_block").alias("_q_block")).distinct()
        sent = data.join(wanted, F.col("cell") == F.col("_cell")).select("cell", "block", F.col("_q_block").alias("q_block"), "vec_id", "x")
        return spread.groupBy(*where).cogroup(sent.groupBy(*where)).applyInArrow(search, OUT)

    home = run(queries.where(F.col("q_cell").isin(cells.tolist())).select("*", F.col("q_cell").alias("cell"), F.lit(float("-inf")).alias("bound")))
    per_block = home.withColumn("nth", F.row_number().over(Window.partitionBy("query_row").orderBy(F.desc("score"), "vec_id"))).where(F.col("nth") == k)
    bounds = per_block.select("query_row", F.col("score").alias("bound")).checkpoint()

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            q, asked, bound = _matrix(batch.column(2), width), _matrix(batch.column(3), dims), batch.column(5).to_numpy()
            reach = np.maximum((q * q).sum(1) + length2 - 2 * bound, 1e-300)
            skip = chi_square_cdf(box_distances(asked, low, high) / reach[:, None], dims) >= sure
            at, cell = np.nonzero(~(skip & np.isfinite(bound)[:, None]))
            part = batch.take(pa.array(at))
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array(cells[cell])], names=[*batch.schema.names, "cell"])

    ready = queries.join(bounds, "query_row", "left").select("query_row", "query_id", "q", "asked", "q_block", F.coalesce("bound", F.lit(float("-inf"))).alias("bound"))
    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in ready.schema)
    found = run(ready.mapInArrow(route, kinds + ", cell bigint"))
    rank = F.row_number().over(Window.partitionBy("query_row").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
