"""Similarity join of documents by the Jaccard similarity of their word n-gram sets, and its components.

Sets are ordered by one global order: shingles common to many documents last, the rest by hash. Two sets that link
share several shingles among the first of each (the prefix), so only prefixes are dealt out, and a document whose
prefix holds too few shingles of others is out. A prefix-tree of the
candidates is walked with many sets at a time: candidates share the overlaps of their common
start, and a subtree goes once the lengths that remain can't reach the overlaps needed.

The documents with a shingle of their prefixes in common are put under the first of them. All who stand under one
document are joined by tree, in blocks of bounded size; large groups are blocks against blocks. What a
block sends back is no list of pairs but at most one link for each document, enough to join what is linked.
Equal sets are one class throughout. Any two sets that link share a prefix shingle, so they stand under one document
and meet: no link between components is lost.

Shingles are 62-bit hashes; classes are 64-bit sums over sets, so that different ones agree by chance about
once in 2**62 pairs. Memory: bit maps are sent out, sized by a count of what they hold up to 64 MB (beyond that they let
surplus rows through), and a sorted list of at most max_common common shingles, which only sets the order.

Cases: null texts, and texts without words, have no shingles and are linked with nothing; with fewer words than
the size the whole sequence is the one shingle. Rows without doc_id take no part in links and have no component.
Rows of equal doc_id are one document that links by any of its texts, which are joined by it. An empty table gives an empty result.
Other columns are left out of account.
"""

from __future__ import annotations

import gc
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import delete, has_columns, shared_dir, written
from twoview.llm.graphs import components
from twoview.llm.text import Chunk, column_chunks, mix, shingle_sets

NUM, DEN = 3, 4  # the similarity from which documents link
COMMON = np.int64(1 << 62)
SLOTS = 29  # of a bit map, at most, as a power of two
BLOCK = 400_000  # shingles
SENT = 2_000_000  # ids sent out whole, at most


def _ceil(a: np.ndarray | int, b: int) -> np.ndarray | int:
    return -(-a // b)


def level(n: np.ndarray) -> np.ndarray:
    """How many common shingles the prefixes of a set of n and of its partners are to show: more than a quoted passage has there."""
    return np.maximum(1, n // 10)


def prefix_length(n: np.ndarray) -> np.ndarray:
    """How many first shingles of a set of n must hold level(n) of the first ones that it shares with any set that it links with."""
    return np.where(n > 0, np.minimum(n, n - _ceil(NUM * n, DEN) + level(n)), 0)


def least_hits(n: np.ndarray) -> np.ndarray:
    """How many shingles that others have too the prefix of a set of n holds if it links with any: the level of its smallest partner."""
    return level(_ceil(NUM * n, DEN))


def needed(n_a: np.ndarray | int, n_b: np.ndarray | int) -> np.ndarray | int:
    """The least overlap of linked sets of n_a and n_b shingles."""
    return _ceil(NUM * (n_a + n_b), NUM + DEN)


def _sets(chunk: Chunk, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Bounds of each text's set, all shingles in order of hash, set sizes, and classes."""
    doc, h = shingle_sets(chunk, size)
    n = np.bincount(doc, minlength=chunk.n)
    bounds = np.append(0, np.cumsum(n))
    total = np.append(np.uint64(0), np.cumsum(mix(h ^ np.uint64(0x5851F42D4C957F2D))))
    cls = (total[bounds[1:]] - total[bounds[:-1]]) ^ (n.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return bounds, (h >> np.uint64(2)).astype(np.int64), n, cls.view(np.int64)


def _lists(values: np.ndarray, bounds: np.ndarray, take: np.ndarray) -> pa.Array:
    """Arrow lists of the first take values between bounds."""
    index = np.arange(take.sum()) + np.repeat(bounds[:-1] - np.cumsum(take) + take, take)
    return pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(take)), pa.int32()), pa.array(values[index]))


class BitMap:
    """A set of longs that may hold more than was put in: two bits each of a power of two, at least 16 a long up to 2**SLOTS in all."""

    def __init__(self, words: np.ndarray) -> None:
        self.words = words

    @staticmethod
    def _places(x: np.ndarray, slots: int) -> tuple[np.ndarray, np.ndarray]:
        h = mix(x.astype(np.uint64) + np.uint64(0x2545F4914F6CDD1D))
        mask = np.uint64(slots - 1)
        return (h & mask).astype(np.int64), ((h >> np.uint64(32)) & mask).astype(np.int64)

    @classmethod
    def of(cls, df: DataFrame, column: str, most: int = SLOTS) -> BitMap:
        """Built by Spark: each task maps its longs to words, and words meet by a bitwise or; 2**most / 64 words at most."""
        slots = 1 << int(np.clip(np.ceil(np.log2(16 * max(df.count(), 1))), 10, most))

        def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                a, b = cls._places(batch.column(0).to_numpy(zero_copy_only=False), slots)
                s = np.concatenate([a, b])
                yield pa.RecordBatch.from_arrays([pa.array((s >> 6).astype(np.int32)), pa.array(np.uint64(1) << (s & 63).astype(np.uint64)).view(pa.int64())], names=["word", "bits"])

        rows = df.select(column).mapInArrow(words, "word int, bits bigint").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()
        out = np.zeros(slots // 64, np.uint64)
        out[rows["word"].to_numpy()] = rows["bits"].to_numpy().view(np.uint64)
        return cls(out)

    def has(self, x: np.ndarray) -> np.ndarray:
        out = np.ones(len(x), bool)
        for s in self._places(x, 64 * len(self.words)):
            out &= (self.words[s >> 6] >> (s & 63).astype(np.uint64)) & np.uint64(1) == 1
        return out


class PrefixTree:
    """Sorted sets as a radix tree: a node has the shingles that all sets below it go on with, and the least and greatest set below."""

    def __init__(self, sets: list[np.ndarray]) -> None:
        self.order = sorted(range(len(sets)), key=lambda i: sets[i].astype(">i8").tobytes())
        self.sets = [sets[i] for i in self.order]
        self.sizes = np.array([len(s) for s in self.sets])
        self.shared = np.zeros(len(sets) + 1, np.int64)
        for i in range(1, len(sets)):
            a, b = self.sets[i - 1], self.sets[i]
            m = min(len(a), len(b))
            same = a[:m] == b[:m]
            self.shared[i] = m if same.all() else int(np.argmin(same))
        self.tokens, at = np.unique(np.concatenate(self.sets), return_inverse=True)
        self.at = np.split(at, np.cumsum(self.sizes)[:-1])

    def linked(self, probes: list[np.ndarray], cells: int = 1 << 23) -> Iterator[tuple[int, np.ndarray]]:
        """For each set of the tree that links with any, its place in the given list and the probes' places."""
        step = int(np.clip(cells // max(len(self.tokens), 1), 8, 256))
        for base in range(0, len(probes), step):
            for place, who in self._walk(probes[base : base + step]):
                yield place, who + base

    def _walk(self, probes: list[np.ndarray]) -> Iterator[tuple[int, np.ndarray]]:
        flat = np.concatenate(probes)
        size = np.array([len(p) for p in probes])
        who = np.repeat(np.arange(len(probes)), size)
        at = np.minimum(np.searchsorted(self.tokens, flat), len(self.tokens) - 1)
        hit = self.tokens[at] == flat
        has = np.zeros((len(self.tokens), len(probes)), np.uint8)
        has[at[hit], who[hit]] = 1
        upto_token = np.cumsum(has, axis=0, dtype=np.int32)
        total = upto_token[-1]
        todo = [(0, len(self.sets), 0, np.arange(len(probes)), np.zeros(len(probes), np.int64))]
        while todo:
            lo, hi, depth, alive, overlap = todo.pop()
            least, most = int(self.sizes[lo:hi].min()), int(self.sizes[lo:hi].max())
            first = self.at[lo]
            end = len(first) if hi - lo == 1 else int(self.shared[lo + 1 : hi].min())
            if end > depth:
                overlap = overlap + has[first[depth:end]][:, alive].sum(0, dtype=np.int64)
            left = total[alive] - (upto_token[first[end - 1], alive] if end else 0)
            able = overlap + np.minimum(left, most - end) >= needed(size[alive], least)
            if not able.any():
                continue
            alive, overlap = alive[able], overlap[able]
            if hi - lo == 1:
                good = (NUM + DEN) * overlap >= NUM * (size[alive] + least)
                if good.any():
                    yield self.order[lo], alive[good]
                continue
            cuts = [lo, *(lo + 1 + np.flatnonzero(self.shared[lo + 1 : hi] == end)).tolist(), hi]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                todo.append((a, b, end, alive, overlap))


def joined(names: list[int], sets: list[np.ndarray], left: list[int], right: list[int]) -> list[tuple[int, int]]:
    """Links (name, name) that join all that is linked between the sets at two lists of places, at most one a set."""
    label = np.arange(len(sets))
    probes = [sets[i] for i in left]
    places = np.array(left)
    for t, who in PrefixTree([sets[i] for i in right]).linked(probes):
        old = np.unique(label[np.append(places[who], right[t])])
        if len(old) > 1:
            label[np.isin(label, old[1:])] = old[0]
    return [(names[label[i]], names[i]) for i in range(len(sets)) if label[i] != i and names[label[i]] != names[i]]


def _ordered(chunk: Chunk, size: int, order: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """_sets with each set in the global order: common shingles (order, ascending) get a high bit and so come last."""
    bounds, tokens, n, cls = _sets(chunk, size)
    if len(order):
        at = np.minimum(np.searchsorted(order, tokens), len(order) - 1)
        tokens = np.where(order[at] == tokens, tokens | COMMON, tokens)
        tokens = tokens[np.lexsort((tokens, np.repeat(np.arange(chunk.n), n)))]
    return bounds, tokens, n, cls


def _verify(batches: Iterator[pa.RecordBatch], size: int, order: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Of rows (a, i, j, block, cls, text), those of one (a, i, j) together, the links between blocks i and j under a."""
    key, names, blocks, sets = None, [], [], []

    def settle() -> pa.RecordBatch:
        _, i, j = key
        left, right = ([k for k, b in enumerate(blocks) if b == x] for x in (i, j))
        good = joined(names, sets, left, right) if left and right and len(sets) > 1 else []
        return pa.RecordBatch.from_arrays([pa.array([x for x, _ in good], pa.int64()), pa.array([y for _, y in good], pa.int64())], names=["a", "b"])

    for batch in batches:
        keys = list(zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True))
        own, wanted = batch.column(3).to_pylist(), batch.column(4).to_pylist()
        for chunk in column_chunks(batch.column(5)):
            bounds, tokens, _, cls = _ordered(chunk, size, order)
            for i in range(chunk.n):
                r = chunk.row0 + i
                if cls[i] != wanted[r]:
                    continue  # another text of the same id
                if keys[r] != key:
                    if names:
                        yield settle()
                    key, names, blocks, sets = keys[r], [], [], []
                names.append(wanted[r])
                blocks.append(own[r])
                sets.append(tokens[bounds[i] : bounds[i + 1]].copy())
    if names:
        yield settle()


def _linked(members: DataFrame, source: DataFrame, ids: DataFrame, size: int, order: Broadcast) -> DataFrame:
    """Links (a, b) among the members (a, cls, n) of each a; ids (cls, doc_id) has a document of each class.

    Texts travel, being smaller than their sets. A group of B blocks sends each text to B pairs of blocks.
    """
    # written, so that a group with many members is a skewed side of a plain join, which Spark splits
    groups = members.groupBy("a").agg(F.ceil(F.sum("n") / BLOCK).alias("parts"), F.count("*").alias("many")).where("many > 1").drop("many").checkpoint()
    own = F.pmod(F.xxhash64("cls"), F.col("parts"))
    dealt = members.join(groups, "a").select("a", "cls", own.alias("block"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("parts") - 1)).alias("other"))
    asked = dealt.join(ids, "cls").select("doc_id", "cls", "a", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block").checkpoint()
    chosen = source.sparkSession.sparkContext.broadcast(BitMap.of(asked, "doc_id"))

    def pick(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(chosen.value.has(batch.column(0).to_numpy())))

    texts = source.where(F.col("doc_id").isNotNull()).mapInArrow(pick, "doc_id bigint, text string").join(asked, "doc_id")
    rows = texts.repartition("a", "i", "j").sortWithinPartitions("a", "i", "j").select("a", "i", "j", "block", "cls", "text")
    return rows.mapInArrow(lambda batches: _verify(batches, size, order.value), "a bigint, b bigint").distinct().checkpoint()


def _free(spark) -> None:
    """Lets Spark drop the shuffle files of plans that nothing refers to any more; it has no call that deletes them outright."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def _common(shared: DataFrame, least: int, most: int) -> np.ndarray:
    """The shingles that least documents or more have in their prefix; a higher bound where they are over most."""
    counts = shared.where(F.col("n") >= least).groupBy(F.floor(F.log2("n")).alias("k")).count().collect()
    total, bound = 0, least
    for r in sorted(counts, key=lambda r: -r.k):
        total += r["count"]
        if total > most:
            bound = max(bound, 2 ** (int(r.k) + 1))
            break
    return np.sort(shared.where(F.col("n") >= bound).select("token").toArrow()["token"].to_numpy())


def ngram_components(docs: DataFrame, *, size: int = 5, common: int = 16, max_common: int = 1_000_000) -> DataFrame:
    """Link documents (doc_id, text) whose word n-gram sets have a Jaccard similarity of 0.75 or more.

    Returns doc_id, n_shingles, component_id (the smallest doc_id that links reach), one row a document row.
    """
    spark = docs.sparkSession
    shared_dir(spark)
    source = has_columns(docs, "doc_id", "text")

    def first_pass(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in column_chunks(batch.column(1)):
                bounds, tokens, n, cls = _sets(chunk, size)
                ids = batch.column(0).slice(chunk.row0, chunk.n)
                take = np.where(ids.is_valid().to_numpy(zero_copy_only=False), prefix_length(n), 0)
                yield pa.RecordBatch.from_arrays([ids, pa.array(n), pa.array(cls), _lists(tokens, bounds, take)], names=["doc_id", "n", "cls", "prefix"])

    sets = written(source.mapInArrow(first_pass, "doc_id bigint, n bigint, cls bigint, prefix array<bigint>"), "sets", **{"parquet.enable.dictionary": "false"})
    by_token = sets.select("cls", F.explode("prefix").alias("token")).groupBy("token").agg(F.min("cls").alias("lo"), F.max("cls").alias("hi"), F.count("*").alias("n"))
    shared = written(by_token.where("lo <> hi").select("token", "n"), "shared")
    _free(spark)
    order = spark.sparkContext.broadcast(_common(shared, common, max_common))
    tokens_map = spark.sparkContext.broadcast(BitMap.of(shared, "token"))

    def touched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, cls, n, prefix = (batch.column(i) for i in range(4))
            off = prefix.offsets.to_numpy()
            hit = np.append(0, np.cumsum(tokens_map.value.has(prefix.values.to_numpy()[off[0] : off[-1]])))
            rows = pa.array(np.flatnonzero(hit[off[1:] - off[0]] - hit[off[:-1] - off[0]] >= least_hits(n.to_numpy())))
            yield pa.RecordBatch.from_arrays([ids.take(rows), cls.take(rows)], names=["doc_id", "cls"])

    active = (
        sets.where(F.col("doc_id").isNotNull() & (F.col("n") > 0))
        .select("doc_id", "cls", "n", "prefix")
        .mapInArrow(touched, "doc_id bigint, cls bigint")
        .groupBy("cls")
        .agg(F.min("doc_id").alias("doc_id"))
        .checkpoint()
    )
    chosen = spark.sparkContext.broadcast(BitMap.of(active, "doc_id"))

    def second_pass(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            batch = batch.filter(pa.array(chosen.value.has(batch.column(0).to_numpy())))
            for chunk in column_chunks(batch.column(1)):
                bounds, tokens, n, cls = _ordered(chunk, size, order.value)
                yield pa.RecordBatch.from_arrays([pa.array(cls), pa.array(n), _lists(tokens, bounds, prefix_length(n))], names=["cls", "n", "set"])

    again = source.where(F.col("doc_id").isNotNull())
    starts = written(again.mapInArrow(second_pass, "cls bigint, n bigint, `set` array<bigint>"), "prefixes", **{"parquet.enable.dictionary": "false"})
    by_first = [F.min("cls").alias("a"), F.max("cls").alias("z"), F.min_by("n", "cls").alias("n_a")]
    shown = written(starts.select("cls", "n", F.explode("set").alias("token")).groupBy("token").agg(*by_first).where("a <> z").select("token"), "groups")
    _free(spark)
    group_map = spark.sparkContext.broadcast(BitMap.of(shown, "token"))

    def grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            off = batch.column(2).offsets.to_numpy()
            tokens = batch.column(2).values.to_numpy()[off[0] : off[-1]]
            owner = np.repeat(np.arange(batch.num_rows), np.diff(off))
            hit = group_map.value.has(tokens)
            rows = pa.array(owner[hit])
            yield pa.RecordBatch.from_arrays([batch.column(0).take(rows), batch.column(1).take(rows), pa.array(tokens[hit])], names=["cls", "n", "token"])

    rows = starts.mapInArrow(grouped, "cls bigint, n bigint, token bigint").join(shown, "token", "left_semi").checkpoint()
    smallest = F.greatest(F.lit(1), F.floor(F.ceil(F.col("n") * NUM / DEN) / 10))
    enough = rows.groupBy("cls", "n").agg(F.count("*").alias("hits")).where(F.col("hits") >= smallest).select("cls")
    rows = rows.join(enough, "cls", "left_semi").checkpoint()
    groups = rows.groupBy("token").agg(*by_first).where("a <> z").drop("z").checkpoint()
    under = rows.join(groups, "token").select("a", "cls", "n", "n_a").dropDuplicates(["a", "cls"]).checkpoint()
    heads = under.select("a", F.col("a").alias("cls"), F.col("n_a").alias("n")).dropDuplicates(["a"])
    members = under.where("a <> cls").select("a", "cls", "n").unionAll(heads)
    _free(spark)
    links = _linked(members, source, active, size, order)
    narrow = written(sets.select("doc_id", "n", "cls"), "classes")
    of_one = narrow.where((F.col("n") > 0) & F.col("doc_id").isNotNull())
    several = of_one.groupBy("doc_id").agg(F.min("cls").alias("a"), F.max("cls").alias("z")).where("a <> z").select("doc_id", "a").checkpoint()
    if not several.isEmpty():
        links = links.unionAll(of_one.join(several, "doc_id").select("a", F.col("cls").alias("b")))
    comp = components(links)
    for sent in (order, tokens_map, chosen, group_map):
        sent.destroy()
    delete(sets, shared, starts, shown)

    classes = of_one.groupBy("cls").agg(F.min("doc_id").alias("first"))
    linked_ids = classes.join(comp, classes.cls == comp.node, "left").select("cls", "first", F.coalesce("comp", "cls").alias("comp"))
    lowest = linked_ids.groupBy("comp").agg(F.min("first").alias("component_id"))
    found = linked_ids.join(lowest, "comp").select("cls", "component_id")
    return (
        narrow.select("doc_id", F.col("n").alias("n_shingles"), F.when((F.col("n") > 0) & F.col("doc_id").isNotNull(), F.col("cls")).alias("cls"))
        .join(found, "cls", "left")
        .select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
    )


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs, with all columns, that stay when of each group of linked documents one does: that of the smallest id.

    Where ids are missing or repeated, rows are numbered and each is a document by itself, so that the first row stays.
    Ids that go are few beside the texts. They are sent out while they are at most SENT; beyond that a bit map
    tells the rows that may go, and only those texts move to meet them.
    """
    ids = docs.groupBy("doc_id").count()
    key = "doc_id"
    if not ids.where(F.col("doc_id").isNull() | (F.col("count") > 1)).isEmpty():
        key = "_row"
        docs = written(docs.withColumn(key, F.monotonically_increasing_id()), "numbered")
    found = ngram_components(docs.select(F.col(key).alias("doc_id"), "text"), **options)
    gone = found.where(F.col("doc_id") != F.col("component_id")).select(F.col("doc_id").alias("_gone")).checkpoint()
    return _without(docs, key, gone, SENT).select(*[c for c in docs.columns if c != "_row"])


def _without(docs: DataFrame, key: str, gone: DataFrame, most: int) -> DataFrame:
    """The rows of docs whose key is not among gone (_gone)."""
    if gone.count() <= most:
        return docs.join(F.broadcast(gone), F.col(key) == F.col("_gone"), "left_anti")
    known, at = docs.sparkSession.sparkContext.broadcast(BitMap.of(gone, "_gone")), docs.columns.index(key)

    def part(maybe: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield batch.filter(pa.array(known.value.has(batch.column(at).to_numpy()) == maybe))

        return docs.mapInArrow(run, docs.schema)

    return part(False).unionAll(part(True).join(gone, F.col(key) == F.col("_gone"), "left_anti"))
