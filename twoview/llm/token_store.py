"""Token ids in a binary store: each document's ids compressed by themselves with one shared dictionary.

A store is a table of blocks, each a row: its least and greatest doc_id, the dictionary's hash, the documents' ids, token counts,
byte offsets, and one blob of independent frames. A document is read from the blocks whose ids span its own, which the
files' statistics tell, and its frame alone is cut out. Parts are files, blocks follow each other in
ascending doc_id, null first, within a file and over files by name; the dictionary is a file beside them, trained on a
bounded sample of serialized id arrays.

Texts are split at white space first and each distinct word is tokenized once while a task's cache holds it; the
tokenizer never joins across white space, so the ids are those of whole texts.

Cases: a null text is an empty one, whose ids are the end id alone. Rows of equal doc_id are stored one after
another. An empty table gives an empty store. Other columns are left out of account.
"""

from __future__ import annotations

import hashlib
import json
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twoview.llm.base import has_columns, shared_dir, written
from twoview.llm.text import Chunk, column_chunks, span_hashes

CACHE_WORDS, YOUNG_WORDS = 1_200_000, 40_000
BLOCK_BYTES = 1 << 20
BLOCK = (
    "part bigint, seq bigint, lo bigint, hi bigint, dict_sha256 string, doc_id array<bigint>, n_tokens array<bigint>, offset array<bigint>, blob binary, tokens bigint"
)


class WordIds:
    """Token ids of the words of chunks, from a cache of words by hash that starts anew when it is full.

    Words come first into a small sorted table, which goes over into the large one now and then.
    """

    def __init__(self, path: str, lower: bool = False) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        made = json.loads(self.tokenizer.to_str())
        folds = any(n["type"] == "Lowercase" for n in [made["normalizer"] or {"type": ""}, *(made["normalizer"] or {}).get("normalizers", [])])
        self.lower, self.folds = lower, folds
        self.suffix = made["model"].get("end_of_word_suffix")
        vocab = self.tokenizer.get_vocab()
        self.closes = np.zeros(max(vocab.values()) + 1, bool)
        if self.suffix:
            self.closes[[i for t, i in vocab.items() if t.endswith(self.suffix)]] = True
        self.clear()

    def clear(self) -> None:
        self.tables = [(np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int32)) for _ in range(2)]
        self.ids, self.used = np.zeros(1 << 16, np.uint32), 0

    @staticmethod
    def _merged(a: tuple, b: tuple) -> tuple:
        keys = np.concatenate([a[0], b[0]])
        order = np.argsort(keys, kind="stable")
        return keys[order], np.concatenate([a[1], b[1]])[order], np.concatenate([a[2], b[2]])[order]

    def _ids(self, texts: list[str], plain: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of some texts one after another, and how many each has.

        Texts of letters alone (plain) go as one text: each gives one word, whose last id says that a word ends.
        """
        count = np.zeros(len(texts), np.int64)
        parts: list[np.ndarray] = [np.zeros(0, np.uint32)] * len(texts)
        joint = np.flatnonzero(plain) if self.suffix else np.zeros(0, np.int64)
        if len(joint):
            got = np.array(self.tokenizer.encode_batch_fast([" ".join([texts[i] for i in joint])], add_special_tokens=False)[0].ids, np.uint32)
            last = np.flatnonzero(self.closes[got]) + 1
            if len(last) == len(joint) and last[-1] == len(got):
                count[joint] = np.diff(last, prepend=0)
                if len(joint) == len(texts):
                    return got, count
                for i, a, b in zip(joint.tolist(), [0, *last[:-1].tolist()], last.tolist(), strict=True):
                    parts[i] = got[a:b]
                plain = plain.copy()
            else:
                plain = np.zeros(len(texts), bool)
        else:
            plain = np.zeros(len(texts), bool)
        rest = np.flatnonzero(~plain)
        for i, e in zip(rest.tolist(), self.tokenizer.encode_batch_fast([texts[i] for i in rest], add_special_tokens=False), strict=True):
            parts[i] = np.array(e.ids, np.uint32)
            count[i] = len(parts[i])
        return np.concatenate(parts) if parts else np.zeros(0, np.uint32), count

    def _learn(self, cp: np.ndarray, starts: np.ndarray, ends: np.ndarray, plain: np.ndarray, h: np.ndarray) -> None:
        """Tokenizes the distinct ones of some spans."""
        h, at = np.unique(h, return_index=True)
        texts = [cp[a:b].tobytes().decode("utf-32-le") for a, b in zip(starts[at].tolist(), ends[at].tolist(), strict=True)]
        ids, count = self._ids(texts, plain[at])
        while self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        self.ids[self.used : self.used + len(ids)] = ids
        first = np.cumsum(count) - count + self.used
        self.used += len(ids)
        self.tables[1] = self._merged(self.tables[1], (h, first, count.astype(np.int32)))

    def _spans(self, chunk: Chunk, cp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Spans to look up: words, cut where letters or digits meet closing marks; which word each is of; which are letters alone."""
        starts, ends = chunk.starts, chunk.ends
        letter = ((cp - np.uint32(97)) < 26) | ((cp - np.uint32(65)) < 26) | (((cp - np.uint32(0xC0)) < 0x40) & (cp != 0xD7) & (cp != 0xF7))
        core = ends.copy()
        if self.suffix and len(starts):
            for _ in range(3):
                mark = cp[core - 1]
                core = core - (((mark == 46) | (mark == 44) | (mark == 33)) & (core - 1 > starts))
            core = np.where(letter[core - 1], core, ends)
        cut = core < ends
        word = np.repeat(np.arange(len(starts)), 1 + cut)
        tail = np.zeros(len(word), bool)
        tail[1:] = word[1:] == word[:-1]
        a = np.where(tail, core[word], starts[word])
        b = np.where(tail, ends[word], core[word])
        total = np.append(0, np.cumsum(letter))
        return a, b, word, total[b] - total[a] == b - a

    def encode(self, chunk: Chunk) -> tuple[np.ndarray, np.ndarray]:
        """All ids of a chunk's words in order, and how many each word has."""
        # special tokens are told by case, so a chunk that may hold one is taken as it is
        fold = self.lower or (self.folds and not (chunk.cp == 60).any())
        cp = chunk.lower if fold else chunk.cp
        starts, ends, word, plain = self._spans(chunk, cp)
        h = span_hashes(cp, starts, ends, chunk.solid)
        if len(self.tables[1][0]) > YOUNG_WORDS:
            self.tables = [self._merged(*self.tables), (np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int32))]
        if len(self.tables[0][0]) > CACHE_WORDS:
            self.clear()
        first, count = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64)
        todo = np.arange(len(h))
        for k in (0, 1, 1):
            keys, start, n = self.tables[k]
            if len(keys) and len(todo):
                at = np.minimum(np.searchsorted(keys, h[todo]), len(keys) - 1)
                hit = keys[at] == h[todo]
                first[todo[hit]], count[todo[hit]] = start[at[hit]], n[at[hit]]
                todo = todo[~hit]
            if k and len(todo):
                self._learn(cp, starts[todo], ends[todo], plain[todo], h[todo])
        index = np.arange(count.sum()) + np.repeat(first - np.cumsum(count) + count, count)
        return self.ids[index], np.bincount(word, count, len(chunk.starts)).astype(np.int64)


_word_ids: dict[tuple[str, bool], WordIds] = {}


def word_ids(path: str, lower: bool = False) -> WordIds:
    """The worker's cache for a tokenizer file."""
    if (path, lower) not in _word_ids:
        _word_ids[path, lower] = WordIds(path, lower)
    return _word_ids[path, lower]


def document_ids(chunk: Chunk, path: str, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids of each text with the end id, one after another, and the bounds of each text."""
    ids, count = word_ids(path).encode(chunk)
    total = np.append(0, np.cumsum(count))
    n = total[chunk.word_off[1:]] - total[chunk.word_off[:-1]]
    bounds = np.append(0, np.cumsum(n + 1))
    out = np.full(bounds[-1], end_id, np.uint32)
    fill = np.ones(len(out), bool)
    fill[bounds[1:] - 1] = False
    out[fill] = ids
    return out, bounds


@dataclass
class TokenStore:
    """A store: its blocks in order of (part, seq), and the dictionary."""

    blocks: DataFrame
    dictionary: bytes

    def documents(self) -> DataFrame:
        """Read all frames back: doc_id, start, n_tokens, ids (little-endian bytes)."""
        spark = self.blocks.sparkSession
        parts = self.blocks.groupBy("part").agg(F.sum("tokens").alias("tokens")).collect()  # one row a part
        base, at = {}, 0
        for r in sorted(parts, key=lambda r: r.part):
            base[r.part] = at
            at += r.tokens
        sent = spark.sparkContext.broadcast((base, self.dictionary))

        def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            base, dictionary = sent.value
            at: dict[int, int] = {}
            opened = _reader(dictionary)
            sha = hashlib.sha256(dictionary).hexdigest()
            for batch in batches:
                for row in batch.to_pylist():
                    if row["dict_sha256"] != sha:
                        raise ValueError("a block was written with another dictionary")
                    part = row["part"]
                    start = at.setdefault(part, base[part])
                    blob, off = row["blob"], row["offset"]
                    ids = [opened.decompress(blob[a:b]) for a, b in zip(off[:-1], off[1:], strict=True)]
                    n = np.array(row["n_tokens"], np.int64)
                    starts = start + np.cumsum(n) - n
                    at[part] = start + int(n.sum())
                    if [len(x) for x in ids] != (4 * n).tolist():
                        raise ValueError("a frame does not hold the tokens of its index")
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(row["doc_id"], pa.int64()), pa.array(starts), pa.array(n), pa.array(ids, pa.binary()), pa.array([zlib.crc32(x) for x in ids], pa.int64())],
                        names=["doc_id", "start", "n_tokens", "ids", "crc"],
                    )

        ordered = self.blocks.repartitionById(max(base, default=0) + 1, F.col("part").cast("int")).sortWithinPartitions("part", "seq")
        return ordered.mapInArrow(read, "doc_id bigint, start bigint, n_tokens bigint, ids binary, crc bigint")

    def get(self, doc_id: int) -> list[np.ndarray]:
        """Ids of a document, from the blocks whose index names it and from its own frames alone."""
        near = self.blocks.where((F.col("lo") <= doc_id) & (F.col("hi") >= doc_id))
        places = near.select("part", "seq", "offset", "blob", F.posexplode("doc_id").alias("nth", "id")).where(F.col("id") == doc_id)
        a, b = F.get("offset", F.col("nth")), F.get("offset", F.col("nth") + 1)
        frames = places.select("part", "seq", "nth", F.substring("blob", (a + 1).cast("int"), (b - a).cast("int")).alias("frame")).collect()
        opened = _reader(self.dictionary)
        return [np.frombuffer(opened.decompress(bytes(r.frame)), "<u4") for r in sorted(frames, key=lambda r: r[:3])]


def _reader(dictionary: bytes) -> zstandard.ZstdDecompressor:
    return zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(dictionary)) if dictionary else zstandard.ZstdDecompressor()


def train_dictionary(docs: DataFrame, path: str, end_id: int, rows: int, size: int) -> bytes:
    """A dictionary of size bytes from the id arrays of rows documents at most, chosen by a hash of all ids; empty if they are too few."""
    n = docs.count()
    share = min(1.0, 4 * rows / max(n, 1))
    texts = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) <= int(share * (1 << 20))).select("text", F.xxhash64("doc_id").alias("h")).orderBy("h").limit(rows).toArrow()["text"]
    samples = []
    for chunk in column_chunks(texts):
        ids, bounds = document_ids(chunk, path, end_id)
        samples += [ids[a:b].tobytes() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
    try:
        return zstandard.train_dictionary(size, samples).as_bytes()
    except zstandard.ZstdError:
        return b""


def write_store(docs: DataFrame, path: str, *, end_id: int, parts: int | None = None, level: int = 3, dict_rows: int = 2000, dict_bytes: int = 64 << 10) -> TokenStore:
    """Tokenize documents (doc_id, text) with a tokenizer file and write them in ascending doc_id."""
    spark = docs.sparkSession
    source = has_columns(docs, "doc_id", "text")
    dictionary = train_dictionary(source, path, end_id, dict_rows, dict_bytes)
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    cuts = source.select(F.percentile_approx("doc_id", [k / parts for k in range(1, parts)] or [0.5], 100 * parts).alias("q")).first().q or []
    cuts = sorted(set(cuts))
    sent = spark.sparkContext.broadcast((dictionary, np.array(cuts, np.int64)))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dictionary, cuts = sent.value
        press = zstandard.ZstdCompressor(level=level, dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None, write_content_size=True)
        for batch in batches:
            for chunk in column_chunks(batch.column(1)):
                ids, bounds = document_ids(chunk, path, end_id)
                frames = [press.compress(ids[a:b].tobytes()) for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                doc = batch.column(0).slice(chunk.row0, chunk.n)
                part = np.searchsorted(cuts, doc.fill_null(-(1 << 63)).to_numpy(zero_copy_only=False), "left")
                yield pa.RecordBatch.from_arrays([doc, pa.array(part), pa.array(np.diff(bounds)), pa.array(frames, pa.binary())], names=["doc_id", "part", "n", "frame"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sha = hashlib.sha256(sent.value[0]).hexdigest()
        rows: list[tuple] = []
        part, seq, size = None, 0, 0

        def block() -> pa.RecordBatch:
            ids, counts, frames = [r[0] for r in rows], [r[1] for r in rows], [r[2] for r in rows]
            offset = [0, *np.cumsum([len(f) for f in frames]).tolist()]
            known = [i for i in ids if i is not None]
            values = [[part], [seq], [min(known, default=None)], [max(known, default=None)], [sha], [ids], [counts], [offset], [b"".join(frames)], [sum(counts)]]
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(values, kinds, strict=True)], names=[c.split()[0] for c in BLOCK.split(", ")])

        for batch in batches:
            for d, p, n, f in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if rows and (p != part or size >= BLOCK_BYTES):
                    yield block()
                    seq = seq + 1 if p == part else 0
                    rows, size = [], 0
                part = p
                rows.append((d, n, f))
                size += len(f)
        if rows:
            yield block()

    frames = source.mapInArrow(encode, "doc_id bigint, part bigint, n bigint, frame binary")
    # a part is a partition and so a file, and their numbers ascend with doc_id
    blocks = frames.repartitionById(len(cuts) + 1, F.col("part").cast("int")).sortWithinPartitions(F.asc_nulls_first("doc_id")).mapInArrow(pack, BLOCK)
    out = f"{shared_dir(spark).rstrip('/')}/twoview/dictionary-{uuid.uuid4().hex}"
    spark.createDataFrame([(hashlib.sha256(dictionary).hexdigest(), bytearray(dictionary))], "sha256 string, dictionary binary").coalesce(1).write.parquet(out)
    return TokenStore(written(blocks, "tokens", compression="none"), bytes(spark.read.parquet(out).first().dictionary))


def default_path(name: str) -> str:
    """Where a public tokenizer's file is."""
    import public_tokenizers

    return public_tokenizers.path(name)


def store_digest(spark: SparkSession, docs: DataFrame, path: str, end_id: int) -> DataFrame:
    """Write a store and read it back: doc_id, start, n_tokens, ids_crc32."""
    return write_store(docs, path, end_id=end_id).documents().select("doc_id", "start", "n_tokens", F.col("crc").alias("ids_crc32"))
