"""Coarse partition: cells of one or two coarse quantizers, probing, and search within the probed cells.

Cells cluster the stored codes by range; a query visits the cells nearest to it, which makes the search an
equi-join on the cell with the bit test as the remaining condition.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twoview.functions import expressions as E
from twoview.operators.model import CodeModel, pack_words, unpack_words
from twoview.operators.quantize import train_pq
from twoview.operators.search import BROADCAST_BYTES, topk
from twoview.operators.vectors import doubles, map_vectors, matrix

PAIRS_AT_ONCE = 1 << 20


@dataclass
class CoarseIndex:
    """Coarse centroids of the parts of a vector; a cell is the number of the parts' centroids together."""

    model: CodeModel  # M parts, 2**c centroids each
    codes: CodeModel
    residual: bool = False

    @property
    def n_cells(self) -> int:
        return self.model.spec.K ** self.model.spec.M

    def cells(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x), np.int64)
        for column in self.model.encode(x).T:
            out = out * self.model.spec.K + column
        return out

    def center(self, cells: np.ndarray) -> np.ndarray:
        numbers = np.stack([cells // self.model.spec.K ** (self.model.spec.M - 1 - m) % self.model.spec.K for m in range(self.model.spec.M)], 1)
        return self.model.decode(numbers)


def probe_order(tables: list[np.ndarray], n_probe: int) -> list[tuple[float, int]]:
    """The n_probe cells of least summed part distances, ties to the smaller cell: a walk over sorted lists with a heap."""
    orders = [np.lexsort((np.arange(len(t)), t)) for t in tables]
    k = len(tables[0])

    def cell(at: tuple[int, ...]) -> tuple[float, int]:
        total, number = 0.0, 0
        for t, o, i in zip(tables, orders, at, strict=True):
            total += float(t[o[i]])
            number = number * k + int(o[i])
        return total, number

    start = (0,) * len(tables)
    heap, seen, out = [(*cell(start), start)], {start}, []
    while heap and len(out) < n_probe:
        d, group = heap[0][0], []
        while heap and heap[0][0] == d:  # cells as near as this one, some of which only come up through it
            _, c, at = heapq.heappop(heap)
            group.append(c)
            for m in range(len(tables)):
                nxt = (*at[:m], at[m] + 1, *at[m + 1 :])
                if nxt[m] < k and nxt not in seen:
                    seen.add(nxt)
                    heapq.heappush(heap, (*cell(nxt), nxt))
        out += [(d, c) for c in sorted(group)]
    return out[:n_probe]


def fit_multi_index(train: DataFrame, dims: int, c: int, codes: CodeModel, parts: int = 2, residual: bool = False, seed: int = 0) -> CoarseIndex:
    """Coarse quantizers of the vector's parts; parts=1 is a plain inverted file."""
    coarse = train_pq(train, parts, c, dims=dims, seed=seed)
    if residual:
        sent = train.sparkSession.sparkContext.broadcast(CoarseIndex(coarse, codes))
        left = map_vectors(train, lambda x: {"embedding": x - sent.value.center(sent.value.cells(x))}, "embedding array<double>")
        spec = codes.spec
        codes = train_pq(left, spec.M, spec.b, dims=dims, seed=seed)
    return CoarseIndex(coarse, codes, residual)


def encode_cells(df: DataFrame, index: CoarseIndex) -> DataFrame:
    """Codes with their cell: (vec_id, cell, w0, ...)."""
    sent = df.sparkSession.sparkContext.broadcast(index)
    spec = index.codes.spec

    def one(x: np.ndarray) -> dict[str, np.ndarray]:
        ix = sent.value
        cells = ix.cells(x)
        words = pack_words(ix.codes.encode(x - ix.center(cells) if ix.residual else x), spec)
        return {"cell": cells} | {f"w{i}": words[:, i] for i in range(spec.n_words)}

    return map_vectors(df, one, "cell bigint, " + ", ".join(f"w{i} bigint" for i in range(spec.n_words)))


def probe_cells(queries: DataFrame, index: CoarseIndex, n_probe: int, quota: int | None = None, sizes: dict[int, int] | None = None) -> DataFrame:
    """Rows (qid, cell, ord, cell_d2, q0, ..., lut): the cells each query visits, nearest first; with a quota, until the
    visited cells hold that many vectors."""
    sent = queries.sparkSession.sparkContext.broadcast((index, sizes or {}))
    spec = index.codes.spec

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ix, size = sent.value
        coarse = ix.model.spec
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x = batch.column(0).to_numpy(), matrix(batch.column(1))
            tables = ix.model.tables(x).reshape(len(x), coarse.M, coarse.K)
            qid, cell, nth, dist, rows = [], [], [], [], []
            for r in range(len(x)):
                found = 0
                for o, (d, c) in enumerate(probe_order(list(tables[r]), n_probe)):
                    qid.append(ids[r])
                    cell.append(c)
                    nth.append(o + 1)
                    dist.append(d)
                    rows.append(r)
                    found += size.get(c, 0)
                    if quota is not None and found >= quota:
                        break
            target = x[rows]
            if ix.residual:
                target = target - ix.center(np.array(cell))
            lut = ix.codes.tables(target)
            words = pack_words(lut.reshape(len(lut), spec.M, spec.K).argmin(2), spec)
            flat = pa.ListArray.from_arrays(pa.array(np.arange(len(lut) + 1) * lut.shape[1], pa.int32()), pa.array(lut.ravel()))
            yield pa.RecordBatch.from_arrays(
                [pa.array(qid), pa.array(cell), pa.array(nth, pa.int32()), pa.array(dist), *[pa.array(words[:, i]) for i in range(spec.n_words)], flat],
                names=["qid", "cell", "ord", "cell_d2", *[f"q{i}" for i in range(spec.n_words)], "lut"],
            )

    schema = "qid bigint, cell bigint, ord int, cell_d2 double, " + ", ".join(f"q{i} bigint" for i in range(spec.n_words)) + ", lut array<double>"
    return queries.select(F.col("vec_id"), doubles().alias("embedding")).mapInArrow(run, schema)


def search_ivf(probes: DataFrame, coded: DataFrame, index: CoarseIndex, k: int, tau: int | None = None, n_probes: int | None = None) -> DataFrame:
    """Join on the cell, bit test as the rest of the condition, then look-ups.

    The probe side is broadcast only while its counted size allows. Beyond that the words of probes alone are dealt by
    cell, and a query's table meets the pairs that are left; search_ivf_dealt makes tables where cells meet.
    """
    spec = index.codes.spec
    w, q = E.word_columns("w", spec.n_words), E.word_columns("q", spec.n_words)
    test = E.hamming(w, q) <= tau if tau is not None else F.lit(True)
    size = (probes.count() if n_probes is None else n_probes) * (96 + 8 * spec.M * spec.K)
    if size <= BROADCAST_BYTES:
        kept = coded.join(F.broadcast(probes), (coded.cell == probes.cell) & test)
    else:
        thin = probes.select("qid", F.col("cell").alias("_cell"), *[f"q{i}" for i in range(spec.n_words)])
        kept = coded.join(thin, (F.col("cell") == F.col("_cell")) & test).drop("_cell")
        by = ["qid", "cell"] if index.residual else ["qid"]
        tables = probes.select(*by, "lut") if index.residual else probes.where("ord = 1").select(*by, "lut")
        kept = kept.join(tables, by)
    return topk(kept.select("qid", "vec_id", E.adc(w, F.col("lut"), spec).alias("score")), k)


def _parts(rows: DataFrame, most: int) -> DataFrame:
    """Cells of more than most rows, with the number of parts that they are cut into."""
    return rows.groupBy("cell").agg(F.count("*").alias("_n")).where(F.col("_n") > most).select("cell", F.ceil(F.col("_n") / most).alias("parts"))


def search_ivf_dealt(
    queries: DataFrame, coded: DataFrame, index: CoarseIndex, k: int, n_probe: int, tau: int | None = None, *, code_rows: int = 65_536, query_rows: int = 16_384, exclude_self: bool = False
) -> DataFrame:
    """The search for any number of queries: raw vectors travel to the cells that they visit, and tables are made there.

    A heavy cell's codes and queries are cut into parts, each part of the one meets each of the other in a task
    of its own, so that no task holds more than code_rows codes and query_rows queries.
    """
    sent, spec = queries.sparkSession.sparkContext.broadcast(index), index.codes.spec

    def visits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coarse = sent.value.model.spec
        for batch in batches:
            if batch.num_rows:
                tables = sent.value.model.tables(matrix(batch.column(1))).reshape(batch.num_rows, coarse.M, coarse.K)
                near = [[c for _, c in probe_order(list(t), n_probe)] for t in tables]
                rows = np.repeat(np.arange(batch.num_rows), [len(c) for c in near])
                part = batch.take(pa.array(rows))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array([c for cells in near for c in cells], pa.int64())], names=["qid", "x", "cell"])

    asked = queries.select(F.col("vec_id").alias("qid"), doubles().alias("x")).mapInArrow(visits, "qid bigint, x array<double>, cell bigint")
    many_codes, many_asked = _parts(coded, code_rows), _parts(asked, query_rows)
    key = ["cell", "c_part", "q_part"]

    def dealt(rows: DataFrame, id_col: str, own: DataFrame, own_name: str, other: DataFrame, other_name: str) -> DataFrame:
        count = F.coalesce("parts", F.lit(1).cast("bigint"))
        cut = rows.join(own, "cell", "left").withColumn(own_name, F.pmod(F.xxhash64(id_col), count)).drop("parts")
        return cut.join(other, "cell", "left").withColumn(other_name, F.explode(F.sequence(F.lit(0).cast("bigint"), count - 1))).drop("parts")

    left = dealt(asked, "qid", many_asked, "q_part", many_codes, "c_part")
    right = dealt(coded, "vec_id", many_codes, "c_part", many_asked, "q_part")
    words = [f"w{i}" for i in range(spec.n_words)]

    def search(a: pa.Table, b: pa.Table) -> pa.Table:
        qid, ids, score = [], [], []
        if a.num_rows and b.num_rows:
            ix, q, own = sent.value, matrix(a["x"]), b["vec_id"].to_numpy()
            if ix.residual:
                q = q - ix.center(a["cell"].to_numpy())
            w = np.stack([b[c].to_numpy() for c in words], 1).view(np.uint64)
            at = unpack_words(w, spec) + np.arange(spec.M) * spec.K
            names = a["qid"].to_numpy()
            size = max(1, min(256, PAIRS_AT_ONCE // len(own)))
            for start in range(0, len(q), size):
                name = names[start : start + size]
                lut = ix.codes.tables(q[start : start + size]).reshape(len(name), -1)
                keep = own != name[:, None] if exclude_self else np.ones((len(name), len(own)), bool)
                if tau is not None:
                    asked_words = pack_words(lut.reshape(len(lut), spec.M, spec.K).argmin(2), spec).view(np.uint64)
                    keep &= np.bitwise_count(w ^ asked_words[:, None]).sum(2) <= tau
                s = np.zeros(keep.shape)
                for m in range(spec.M):
                    s += lut[:, at[:, m]]
                if len(own) > k:
                    s[~keep] = np.inf
                    keep &= s <= np.partition(s, k - 1, axis=1)[:, k - 1 : k]
                row, col = np.nonzero(keep)
                order = np.lexsort((own[col], s[row, col], row))
                row, col = row[order], col[order]
                best = np.arange(len(row)) - np.searchsorted(row, row) < k
                row, col = row[best], col[best]
                qid.append(name[row])
                ids.append(own[col])
                score.append(s[row, col])
        joined = [np.concatenate(v) if v else np.zeros(0, t) for v, t in ((qid, np.int64), (ids, np.int64), (score, float))]
        return pa.table(dict(zip(("qid", "vec_id", "score"), joined, strict=True)))

    found = left.groupBy(*key).cogroup(right.groupBy(*key)).applyInArrow(search, "qid bigint, vec_id bigint, score double")
    return topk(found, k)


def search_ivf_salted(probes: DataFrame, coded: DataFrame, index: CoarseIndex, k: int, tau: int | None = None, salts: int = 8) -> DataFrame:
    """The same with each cell's codes dealt to several tasks, and probes sent to all of them: for cells of many rows."""
    left = coded.withColumn("salt", F.pmod(F.xxhash64("vec_id"), F.lit(salts)))
    right = probes.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))))
    spec = index.codes.spec
    w, q = E.word_columns("w", spec.n_words), E.word_columns("q", spec.n_words)
    joined = left.join(right.hint("shuffle_hash"), ["cell", "salt"])
    if tau is not None:
        joined = joined.where(E.hamming(w, q) <= tau)
    return topk(joined.select("qid", "vec_id", E.adc(w, F.col("lut"), spec).alias("score")), k)


def probe_cells_sql(tables: DataFrame, n_probe: int) -> DataFrame:
    """Probing of two parts in plain SQL operators: tables (qid, d_u, d_v) are arrays of part distances.

    All pairs of a query's cells are ranked, so this is for few centroids; the walk above gives the same prefix.
    """
    u = tables.select("qid", "d_v", F.posexplode("d_u").alias("u", "du"))
    cells = u.select("qid", "u", "du", F.posexplode("d_v").alias("v", "dv"), F.size("d_v").alias("n"))
    scored = cells.select("qid", (F.col("u") * F.col("n") + F.col("v")).cast("bigint").alias("cell"), (F.col("du") + F.col("dv")).alias("cell_d2"))
    w = Window.partitionBy("qid").orderBy("cell_d2", "cell")
    return scored.withColumn("ord", F.row_number().over(w)).where(F.col("ord") <= n_probe)


def autotune(queries: DataFrame, truth: DataFrame, coded: DataFrame, index: CoarseIndex, n_probes: list[int], taus: list[int]) -> DataFrame:
    """Settings (n_probe, tau) with their candidates, look-ups and recall@1, and whether no cheaper one is as good.

    One pass over the most probes: a pair counts for every setting that admits it.
    """
    from twoview.operators.calibrate import pareto

    spec = index.codes.spec
    w, q = E.word_columns("w", spec.n_words), E.word_columns("q", spec.n_words)
    probes = probe_cells(queries, index, max(n_probes))
    pairs = coded.join(probes, "cell").select("qid", "vec_id", "ord", E.hamming(w, q).alias("h"), E.adc(w, F.col("lut"), spec).alias("score"))
    spark = queries.sparkSession
    grid = spark.createDataFrame([(p, t) for p in n_probes for t in taus], "n_probe int, tau int")
    fit = pairs.join(F.broadcast(grid), F.col("ord") <= F.col("n_probe"))
    kept = F.when(F.col("h") <= F.col("tau"), F.struct("score", "vec_id"))
    per = fit.groupBy("n_probe", "tau", "qid").agg(F.count("*").alias("candidates"), F.count(kept).alias("lookups"), F.min(kept).alias("best"))
    first = truth.where("rk = 1").select("qid", F.col("vec_id").alias("true_id"))
    n = first.select(F.count("*").alias("nq"))
    hits = per.join(first, "qid").groupBy("n_probe", "tau").agg(F.sum("candidates").alias("candidates"), F.sum("lookups").alias("lookups"), F.sum(F.coalesce((F.col("best.vec_id") == F.col("true_id")).cast("int"), F.lit(0))).alias("hits"))
    full = grid.join(hits, ["n_probe", "tau"], "left").crossJoin(F.broadcast(n)).select("n_probe", "tau", F.coalesce("candidates", F.lit(0)).alias("candidates"), F.coalesce("lookups", F.lit(0)).alias("lookups"), (F.coalesce("hits", F.lit(0)) / F.col("nq")).alias("recall"))
    cost = full.withColumn("cost", F.col("candidates") * spec.n_words + F.col("lookups") * spec.M)
    return pareto(cost, "cost", "recall")


@dataclass
class PipelineSpec:
    """A written form of the whole index, as 'rot8_64,mi2x3,pq8': rotation to 64 dimensions in 8 blocks, 2 parts of 2**3 cells, codes of 8 numbers."""

    rotation: tuple[int, int] | None
    parts: int
    cell_bits: int
    M: int

    @classmethod
    def parse(cls, text: str) -> PipelineSpec:
        rotation, parts, cell_bits, M = None, 1, 0, 0
        for item in text.split(","):
            if item.startswith("rot"):
                a, b = item[3:].split("_")
                rotation = (int(a), int(b))
            elif item.startswith("mi"):
                parts, cell_bits = (int(v) for v in item[2:].split("x"))
            elif item.startswith("ivf"):
                parts, cell_bits = 1, int(item[3:])
            elif item.startswith("pq"):
                M = int(item[2:])
            else:
                raise ValueError(f"unknown item {item!r}")
        if not M:
            raise ValueError("no pq item")
        return cls(rotation, parts, cell_bits, M)


def fit_pipeline(train: DataFrame, dims: int, text: str, b: int = 4, seed: int = 0, n_iter: int = 20_000, construction: str = "dist_assigned") -> tuple[CoarseIndex | CodeModel, DataFrame]:
    """What a written spec asks for, and a function's worth of vectors: the training set after the rotation."""
    from twoview.operators.assignment import fit_assignment
    from twoview.operators.linear import balanced_rotation
    from twoview.operators.vectors import apply_map

    spec = PipelineSpec.parse(text)
    if spec.rotation:
        rotation = balanced_rotation(train, dims, spec.rotation[0], spec.rotation[1])
        train, dims = apply_map(train, rotation), spec.rotation[1]
    model = train_pq(train, spec.M, b, dims=dims, seed=seed)
    if construction != "plain":
        model, _ = fit_assignment(train.sparkSession, model, construction, n_iter=n_iter, seed=seed)
    if spec.rotation:
        model.info["rotation"] = rotation
    if not spec.cell_bits:
        return model, train
    return fit_multi_index(train, dims, spec.cell_bits, model, spec.parts, seed=seed), train
