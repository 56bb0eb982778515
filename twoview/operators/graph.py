"""k-NN graphs of all vectors, their refinement, random walks on them, and modes."""

from __future__ import annotations

import warnings
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twoview.functions import expressions as E
from twoview.operators.coarse import CoarseIndex, encode_cells, search_ivf_dealt
from twoview.operators.search import Nearest
from twoview.operators.vectors import doubles, matrix


def _top(edges: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("src").orderBy("dist", "dst")
    return edges.withColumn("rk", F.row_number().over(w)).where(F.col("rk") <= k).select("src", "dst", "rk", "dist")


def knn_graph_exact(df: DataFrame, k: int, tile_rows: int = 16_384) -> DataFrame:
    """The true graph (src, dst, rk, dist) of squared distances: all pairs, in tiles of about tile_rows by tile_rows.

    Each pair of tiles meets in a task, which takes its distances from matrix products and sends on k rows a node.
    """
    v = df.select("vec_id", doubles().alias("x"))
    tiles = max(4, -(-v.count() // tile_rows))
    v = v.withColumn("tile", F.pmod(F.xxhash64("vec_id"), F.lit(tiles)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))
    a = v.select("vec_id", "x", F.col("tile").alias("ta"), every.alias("tb"))
    b = v.select("vec_id", "x", F.col("tile").alias("tb"), every.alias("ta"))

    def meet(a: pa.Table, b: pa.Table) -> pa.Table:
        best = Nearest(a["vec_id"].to_numpy(), matrix(a["x"]), k, exclude_self=True)
        if a.num_rows and b.num_rows:
            best.see(b["vec_id"].to_numpy(), matrix(b["x"]))
        return pa.table(dict(zip(("src", "dst", "dist"), best.columns(), strict=True)))

    near = a.groupBy("ta", "tb").cogroup(b.groupBy("ta", "tb")).applyInArrow(meet, "src bigint, dst bigint, dist double")
    return _top(near, k)


def knn_graph(df: DataFrame, index: CoarseIndex, k: int, n_probe: int, tau: int | None = None, side: str = "raw", **sizes: int) -> DataFrame:
    """Every vector asks the index for its k nearest but itself: vectors travel to the cells that they visit, never all pairs.

    side 'raw': estimates from the raw vector; 'code': from its own code, as when raw vectors are gone. Tables are
    made where a cell's codes and its visitors meet, and heavy cells are cut on both sides (sizes, of search_ivf_dealt).
    """
    coded = encode_cells(df, index)
    if side == "code":
        from twoview.operators.quantize import decode, encode

        df = decode(encode(df, index.codes, numbers=True).select("vec_id", "codes"), index.codes)
    found = search_ivf_dealt(df, coded, index, k, n_probe, tau, exclude_self=True, **sizes)
    return found.select(F.col("qid").alias("src"), F.col("vec_id").alias("dst"), "rk", F.col("score").alias("dist"))


def graph_descent(graph: DataFrame, vectors: DataFrame, k: int, rounds: int = 1, hub: int = 1024) -> DataFrame:
    """Neighbours of neighbours are proposed, measured on raw vectors, and the best k stay; a checkpoint each round.

    A node's neighbours meet with their vectors in a task, which measures all their pairs and sends on each one's k nearest; pairs
    never become rows. The edges of a node with many are cut into parts of about hub, and each pair of parts meets by itself.
    """
    x = vectors.select("vec_id", doubles().alias("x"))

    def ends(column: str, name: str) -> DataFrame:
        return x.select(F.col("vec_id").alias(column), F.col("x").alias(name))

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for node, v, src in _runs(batches):
            row, col, dist = _nearest_pairs(node[src], v[src], node[~src], v[~src], k)
            yield pa.RecordBatch.from_arrays([pa.array(node[src][row]), pa.array(node[~src][col]), pa.array(dist)], names=["src", "dst", "dist"])

    for _ in range(rounds):
        e = graph.select("src", "dst")
        both = e.unionAll(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        parts = both.groupBy(F.col("src").alias("mid")).agg(F.ceil(F.count("*") / hub).alias("parts")).where("parts > 1")
        at = both.select(F.col("src").alias("mid"), F.col("dst").alias("vec_id")).distinct().join(x, "vec_id").join(parts, "mid", "left")
        n = F.coalesce("parts", F.lit(1).cast("bigint"))
        every = F.explode(F.sequence(F.lit(0).cast("bigint"), n - 1))
        own = F.pmod(F.xxhash64("vec_id"), n)
        key = ["mid", "a_part", "b_part"]
        members = at.select("mid", own.alias("a_part"), every.alias("b_part"), F.lit(True).alias("is_src"), "vec_id", "x")
        members = members.unionAll(at.select("mid", every.alias("a_part"), own.alias("b_part"), F.lit(False).alias("is_src"), "vec_id", "x"))
        proposed = members.repartition(*key).sortWithinPartitions(*key).mapInArrow(meet, "src bigint, dst bigint, dist double")
        kept = e.join(ends("src", "a"), "src").join(ends("dst", "b"), "dst").select("src", "dst", E.l2sq(F.col("a"), F.col("b")).alias("dist"))
        graph = _top(proposed.unionAll(kept).groupBy("src", "dst").agg(F.min("dist").alias("dist")), k)
        if rounds > 1:
            graph = graph.checkpoint()
    return graph


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Ids, vectors and sides of each run of rows (mid, a_part, b_part, is_src, vec_id, x) with one key, over batches sorted by key."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = np.stack([batch.column(i).to_numpy() for i in range(3)], 1)
        edges = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(1)) + 1).tolist(), len(keys)]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            key = tuple(keys[a].tolist())
            if held and key != last:
                yield _run_of(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = key
    if held:
        yield _run_of(held)


def _run_of(held: list[pa.RecordBatch]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    t = pa.Table.from_batches(held)
    return t["vec_id"].to_numpy(), matrix(t["x"]), t["is_src"].to_numpy()


def _nearest_pairs(a_id: np.ndarray, a: np.ndarray, b_id: np.ndarray, b: np.ndarray, k: int, pairs: int = 1 << 20) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of a, rows of b and squared distances (summed from the left) of the k nearest b of other id to each a, equal ones by id."""
    found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
    size = max(1, pairs // max(len(b), 1))
    for at in range(0, len(a) if len(b) else 0, size):
        part = a[at : at + size]
        d = np.zeros((len(part), len(b)))
        for x, y in zip(part.T, b.T, strict=True):
            d += (x[:, None] - y) ** 2
        other = a_id[at : at + size, None] != b_id
        near = np.where(other, d, np.inf)
        reach = np.partition(near, k - 1, axis=1)[:, k - 1 : k] if len(b) > k else np.inf
        row, col = np.nonzero(other & (near <= reach))
        order = np.lexsort((b_id[col], d[row, col], row))
        row, col = row[order], col[order]
        best = np.arange(len(row)) - np.searchsorted(row, row) < k
        row, col = row[best], col[best]
        found.append((at + row, col, d[row, col]))
    return tuple(np.concatenate(v) for v in zip(*found, strict=True))


def weighted_edges(graph: DataFrame, weights: str = "uniform", symmetrize: bool = True) -> DataFrame:
    """Edges (src, dst, w), and dist where they are not symmetrized.

    weights: 'uniform', 'inverse' distance, or 'kernel' of the mean distance; symmetrize adds each edge's reverse and weighs both alike.
    """
    e = graph.select("src", "dst", "dist")
    if weights == "kernel":
        scale = e.agg(F.avg("dist").alias("_s"))
        e = e.crossJoin(F.broadcast(scale)).withColumn("w", F.exp(-F.col("dist") / F.greatest("_s", F.lit(1e-12)))).drop("_s")
    else:
        e = e.withColumn("w", F.lit(1.0) if weights == "uniform" else 1 / (F.col("dist") + 1e-9))
    if symmetrize:
        back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "dist", "w")
        e = e.unionAll(back).groupBy("src", "dst").agg(F.max("w").alias("w"))
    return e


def transitions(graph: DataFrame, weights: str = "uniform", symmetrize: bool = True) -> DataFrame:
    """Edges (src, dst, p) with each node's chances summing to one; arguments as of weighted_edges."""
    e = weighted_edges(graph, weights, symmetrize)
    total = e.groupBy("src").agg(F.sum("w").alias("t"))
    return e.join(total, "src").select("src", "dst", (F.col("w") / F.col("t")).alias("p"))


def walk_step(p: DataFrame, steps: DataFrame, nodes: DataFrame, lazy: float = 0.0, teleport: float = 0.0) -> DataFrame:
    """One step of the walk: p (node, p) after it. Mass at nodes without edges, and teleported mass, goes evenly to all."""
    moved = steps.join(p, steps.src == p.node).groupBy(F.col("dst").alias("node")).agg(F.sum(steps.p * p.p).alias("in"))
    sums = moved.agg(F.coalesce(F.sum("in"), F.lit(0.0)).alias("moved")).crossJoin(nodes.agg(F.count("*").alias("n")))
    spread = nodes.join(moved, "node", "left").join(p, "node").crossJoin(F.broadcast(sums))
    flow = F.coalesce(F.col("in"), F.lit(0.0)) + (1 - F.col("moved")) / F.col("n")
    go = (1 - teleport) * flow + teleport / F.col("n")
    return spread.select("node", (lazy * F.col("p") + (1 - lazy) * go).alias("p"))


def stationary(graph: DataFrame, *, weights: str = "uniform", symmetrize: bool = True, teleport: float = 0.0, lazy: float = 0.2, tol: float = 1e-9, max_iter: int = 100, checkpoint_every: int = 5) -> DataFrame:
    """Where a random walk ends up: (node, p). A lazy step keeps it from swinging between two halves.

    Lazy steps are edges from each node to itself, so that a round is one join and one sum. Rounds with dead ends or
    teleports read the last round's result more than once, so each of them ends in a checkpoint; others
    do every few rounds.
    """
    steps = transitions(graph, weights, symmetrize)
    nodes = graph.select(F.col("src").alias("node")).union(graph.select("dst")).distinct().checkpoint()
    n = nodes.count()
    p = nodes.withColumn("p", F.lit(1.0 / max(n, 1)))
    plain = teleport == 0 and nodes.join(steps.select(F.col("src").alias("node")), "node", "left_anti").isEmpty()
    if plain:
        stay = nodes.select(F.col("node").alias("src"), F.col("node").alias("dst"), F.lit(float(lazy)).alias("p"))
        steps = steps.select("src", "dst", (F.col("p") * (1 - lazy)).alias("p")).unionAll(stay)
    steps = steps.checkpoint()
    last = p
    for i in range(1, max_iter + 1):
        if plain:
            p = steps.join(p.select("node", F.col("p").alias("at")), steps.src == F.col("node")).groupBy(F.col("dst").alias("node")).agg(F.sum(F.col("p") * F.col("at")).alias("p"))
            if i % checkpoint_every and i < max_iter:
                continue
        else:
            p = walk_step(p, steps, nodes, lazy, teleport)
        p = p.checkpoint()
        gap = p.join(last.withColumnRenamed("p", "old"), "node").agg(F.sum(F.abs(F.col("p") - F.col("old"))).alias("d")).first().d
        if gap is None or gap < tol:
            break
        last = p
    else:
        warnings.warn(f"the walk has not settled to {tol} in {max_iter} rounds", stacklevel=2)
    return p


def settled(graph: DataFrame, weights: str = "uniform") -> DataFrame:
    """Where a random walk on the symmetrized graph ends, in closed form: (node, p), in proportion to the weights of a node's edges.

    A graph of several parts has more ends than this one; they differ by a factor a part, so that neighbours compare alike.
    """
    at = weighted_edges(graph, weights).groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("t"))
    return at.crossJoin(F.broadcast(at.agg(F.sum("t").alias("all")))).select("node", (F.col("t") / F.col("all")).alias("p"))


def modes(graph: DataFrame, p: DataFrame, strict: bool = True) -> DataFrame:
    """Nodes no neighbour of which is likelier: (node, p, is_mode). strict: equal neighbours of smaller id win."""
    near = graph.select("src", "dst").join(p.select(F.col("node").alias("dst"), F.col("p").alias("pn")), "dst")
    best = near.groupBy("src").agg(F.max("pn").alias("top"), F.min(F.when(F.col("pn").isNotNull(), F.struct(-F.col("pn"), "dst"))).alias("first"))
    j = p.join(best, p.node == best.src, "left")
    wins = F.col("p") > F.col("top")
    ties = (F.col("p") == F.col("top")) & ((F.col("node") < F.col("first.dst")) if strict else F.lit(True))
    return j.select("node", "p", F.coalesce(wins | ties, F.lit(True)).alias("is_mode"))


def mode_gallery(graph: DataFrame, flagged: DataFrame, n: int) -> DataFrame:
    """Each mode with its n closest neighbours, nearest first."""
    m = flagged.where("is_mode").select("node", "p")
    return m.join(graph, m.node == graph.src).where(F.col("rk") <= n).select("node", "p", "rk", "dst", "dist")


def graph_stats(graph: DataFrame, truth: DataFrame | None = None) -> DataFrame:
    """Edges, nodes, greatest in-degree, share of edges that go both ways, recall against a true graph."""
    back = graph.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    parts = [
        graph.agg(F.count("*").alias("edges"), F.countDistinct("src").alias("nodes")),
        graph.groupBy("dst").count().agg(F.max("count").alias("max_in_degree")),
        graph.select("src", "dst").join(back, ["src", "dst"], "left_semi").agg(F.count("*").alias("mutual")),
    ]
    if truth is not None:
        parts.append(truth.select("src", "dst").join(graph.select("src", "dst"), ["src", "dst"], "left_semi").agg(F.count("*").alias("true_found")))
        parts.append(truth.agg(F.count("*").alias("true_edges")))
    return reduce(lambda a, b: a.crossJoin(b), parts)
