"""Language-model scores by causal self-attention over subword ids, and a word-count base.

Subword ids are grouped into classes: common ids have one each, others share the class of ids that come in like
company. One layer of self-attention, trained in numpy, gives the chance of the next class from the classes before
it; within a class an id has its share of the class's training tokens that come right after a token of the class
before it, smoothed by its share of all tokens of its class. So every text has a probability.
Texts are scored in windows that overlap: each token once, with the earlier part of its window as context.

The base, the classes and the shares within classes count all training documents. Words that are common enough for a
table of at most max_table entries are looked up in it, all others meet their counts in a join. All training texts fit the
weights: groups of about GROUP of them, dealt by a hash, are gone through, each by itself and in the hash's order, with every
window of every text (one in refine_every, if that is set higher), and the groups' weights are averaged. Where that pass sets out
from comes from at most fit_tokens tokens, chosen by a hash. A row that repeats with its id and text gives its windows once there.
So scores do not depend on how rows are dealt to tasks, but for the rounding of sums.

Cases: a null text is an empty one, whose one token is the end. Without training documents all counts are
0 and the weights are those of the start. Rows are scored by themselves, repeated ids or not. An empty
table gives an empty result. Other columns are left out of account.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import has_columns, written
from twoview.llm.text import Chunk, column_chunks, mix
from twoview.llm.token_store import word_ids

CLASSES, OWN = 128, 96
WIDTH, KEY, HIDDEN = 24, 8, 24
WINDOW, CONTEXT = 32, 4
SIDES = 2 * (OWN + 1)
BLOCKS = 256
GROUP, PARTS = 1024, 2048
POOL = 100_000
END_WORD = np.array([0x5BD1E9955BD1E995], np.uint64)


@dataclass
class Weights:
    """The parameters, by name, of the attention model."""

    p: dict[str, np.ndarray]

    @classmethod
    def fresh(cls, rng: np.random.Generator) -> Weights:
        def n(*shape: int, scale: float) -> np.ndarray:
            return rng.normal(0, scale, shape).astype(np.float32)

        d = WIDTH
        return cls(
            {
                "now": n(CLASSES, d, scale=0.3),
                "last": n(CLASSES, d, scale=0.3),
                "q": n(d, KEY, scale=0.2),
                "k": n(d, KEY, scale=0.2),
                "v": n(d, d, scale=0.2),
                "far": np.zeros(WINDOW, np.float32),
                "in": n(d, HIDDEN, scale=0.2),
                "out": n(HIDDEN, d, scale=0.1),
                "top": n(d, CLASSES, scale=0.1),
                "bias": np.zeros(CLASSES, np.float32),
            }
        )

    def flat(self) -> np.ndarray:
        return np.concatenate([self.p[k].ravel() for k in sorted(self.p)])

    def of_flat(self, x: np.ndarray) -> Weights:
        out, at = {}, 0
        for k in sorted(self.p):
            out[k] = x[at : at + self.p[k].size].reshape(self.p[k].shape).astype(np.float32)
            at += self.p[k].size
        return Weights(out)


_FUTURE = np.triu(np.full((WINDOW, WINDOW), -1e9, np.float32), 1)
_BACK = np.maximum(np.arange(WINDOW)[:, None] - np.arange(WINDOW)[None, :], 0)


def forward(w: Weights, now: np.ndarray, last: np.ndarray) -> dict[str, np.ndarray]:
    """Class logits at each place of windows of input classes (rows of WINDOW), with what the gradient needs."""
    p, b = w.p, len(now)
    flat = p["now"].take(now.ravel(), 0)
    flat += p["last"].take(last.ravel(), 0)
    qkv = (flat @ np.concatenate([p["q"] * np.float32(KEY**-0.5), p["k"], p["v"]], 1)).reshape(b, WINDOW, -1)
    q, k, v = qkv[..., :KEY], qkv[..., KEY : 2 * KEY], qkv[..., 2 * KEY :]
    s = q @ k.transpose(0, 2, 1)
    s += p["far"][_BACK] + _FUTURE
    np.exp(np.minimum(s, 40, out=s), out=s)
    s /= s.sum(-1, keepdims=True)
    o = s @ v
    y = flat + o.reshape(-1, WIDTH)
    h = y @ p["in"]
    np.maximum(h, 0, out=h)
    z = h @ p["out"]
    z += y
    logits = z @ p["top"]
    logits += p["bias"]
    return {"x": flat, "q": q, "k": k, "v": v, "a": s, "o": o, "y": y, "h": h, "z": z, "logits": logits}


def _sums(dx: np.ndarray, index: np.ndarray) -> np.ndarray:
    """Sums of the rows that share a class."""
    order = np.argsort(index, kind="stable")
    at = index[order]
    first = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
    out = np.zeros((CLASSES, dx.shape[1]), dx.dtype)
    out[at[first]] = np.add.reduceat(dx.take(order, 0), first, axis=0)
    return out


def gradient(w: Weights, now: np.ndarray, last: np.ndarray, target: np.ndarray, use: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """Mean loss (natural logarithm) at the places in use, and its gradient.

    The sums over classes and over places before, by which chances are divided, are left to the narrower arrays after them.
    """
    p, b = w.p, len(now)
    first = np.concatenate([p["q"] * np.float32(KEY**-0.5), p["k"], p["v"]], 1)
    top = np.concatenate([p["top"], p["bias"][None]])
    x = p["now"].take(now.ravel(), 0)
    x += p["last"].take(last.ravel(), 0)
    qkv = (x @ first).reshape(b, WINDOW, -1)
    q, k, v = qkv[..., :KEY], qkv[..., KEY : 2 * KEY], qkv[..., 2 * KEY :]
    s = q @ k.transpose(0, 2, 1)
    s += p["far"][_BACK] + _FUTURE
    np.exp(np.minimum(s, 40, out=s), out=s)
    part = (1 / (s @ np.ones(WINDOW, s.dtype)))[..., None]
    o = s @ v
    o *= part
    y = x + o.reshape(-1, WIDTH)
    h = y @ p["in"]
    np.maximum(h, 0, out=h)
    z = h @ p["out"]
    z += y

    places, ones = np.flatnonzero(use.ravel()), np.ones(CLASSES, top.dtype)
    held = np.ones((len(places), WIDTH + 1), top.dtype)
    held[:, :WIDTH] = z.take(places, 0)
    d, t, rows = held @ top, target.ravel().take(places), np.arange(len(places))
    own = d[rows, t]
    np.exp(d, out=d)
    total = d @ ones
    if len(places) and not (total.max() < 1e30 and total.min() > 1e-30):  # weights of a size that training does not reach
        d = held @ top
        d -= d.max(1, keepdims=True)
        own = d[rows, t]
        np.exp(d, out=d)
        total = d @ ones
    count = max(float(len(places)), 1.0)
    loss = float(np.minimum(np.log(total) - own, -np.log(1e-12)).sum() / count)
    d[rows, t] -= total
    each = (1 / (total * count)).astype(top.dtype)[:, None]
    held *= each
    g = {"top": (d.T @ held).T}
    g["bias"], g["top"] = g["top"][WIDTH], g["top"][:WIDTH]
    dz = np.zeros_like(z)
    dz[places] = (d @ p["top"].T) * each
    g["out"] = h.T @ dz
    dh = dz @ p["out"].T
    dh *= h > 0
    g["in"] = y.T @ dh
    dy = dh @ p["in"].T
    dy += dz
    cut = dy.reshape(b, WINDOW, WIDTH) * part
    ds = cut @ v.transpose(0, 2, 1)
    ds -= np.einsum("bij,bij->bi", cut, o)[..., None]
    ds *= s
    g["far"] = np.bincount(_BACK.ravel(), ds.sum(0).ravel(), WINDOW).astype(np.float32)
    dqkv = np.empty((b, WINDOW, 2 * KEY + WIDTH), dy.dtype)
    np.matmul(ds, k, out=dqkv[..., :KEY])
    np.matmul(ds.transpose(0, 2, 1), q, out=dqkv[..., KEY : 2 * KEY])
    np.matmul(s.transpose(0, 2, 1), cut, out=dqkv[..., 2 * KEY :])
    dqkv = dqkv.reshape(len(dy), -1)
    gx = x.T @ dqkv
    g["q"], g["k"], g["v"] = gx[:, :KEY] * np.float32(KEY**-0.5), gx[:, KEY : 2 * KEY], gx[:, 2 * KEY :]
    dy += dqkv @ first.T
    g["now"], g["last"] = _sums(dy, now.ravel()), _sums(dy, last.ravel())
    return loss, g


class Fitter:
    """Steps with running means of the gradient and its square; the weights become parts of one array."""

    def __init__(self, w: Weights, rate: float) -> None:
        self.w, self.rate, self.n = w, rate, 0
        self.x, at = w.flat(), 0
        for k in sorted(w.p):
            w.p[k], at = self.x[at : at + w.p[k].size].reshape(w.p[k].shape), at + w.p[k].size
        self.m, self.s = np.zeros_like(self.x), np.zeros_like(self.x)

    def step(self, now: np.ndarray, last: np.ndarray, target: np.ndarray, use: np.ndarray, rate: float | None = None) -> float:
        loss, g = gradient(self.w, now, last, target, use)
        self.n += 1
        v = Weights(g).flat()
        self.m += 0.1 * (v - self.m)
        self.s += 0.01 * (v * v - self.s)
        fair = np.sqrt(self.s / (1 - 0.99**self.n))
        fair += 1e-8
        self.x -= (rate or self.rate) / (1 - 0.9**self.n) * self.m / fair
        return loss


def windows_of(classes: np.ndarray, bounds: np.ndarray, end: int, every: int = 1, turn: np.ndarray | int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Windows over texts that lie one after another: classes before, two before, at each place; places to score; the tokens' index.

    One window in every of each text, and at least one; which one is said by turn, one number or one a text.
    """
    n, start = np.diff(bounds).astype(np.int32), bounds[:-1].astype(np.int32)
    step = WINDOW - CONTEXT
    count = np.maximum(1, -(-(n - CONTEXT) // step))
    text = np.repeat(np.arange(len(n), dtype=np.int32), count)
    k = np.arange(len(text), dtype=np.int32) - np.repeat((np.cumsum(count) - count).astype(np.int32), count)
    if every > 1:
        kept = k % every == (turn % np.minimum(count, every))[text]
        text, k = text[kept], k[kept]
    padded = np.full(len(classes) + 2 * len(n), end, np.uint8)  # two ends before each text
    fill = np.ones(len(padded), bool)
    fill[bounds[:-1] + 2 * np.arange(len(n))] = False
    fill[bounds[:-1] + 2 * np.arange(len(n)) + 1] = False
    padded[fill] = classes
    place = np.arange(WINDOW, dtype=np.int32)
    left = n[text] - k * np.int32(step)
    index = np.minimum(place, left[:, None] - 1) + (start[text] + k * np.int32(step))[:, None]
    use = place < left[:, None]
    use[:, :CONTEXT] &= (k == 0)[:, None]
    at = index + 2 * text[:, None]
    return padded[at + 1], padded[at], padded[at + 2], use, index


def log_chances(w: Weights, classes: np.ndarray, bounds: np.ndarray, end: int, batch: int = 64) -> np.ndarray:
    """Natural logarithm of each token's class's chance given its window; each token is scored in one window."""
    before, earlier, target, use, index = windows_of(classes, bounds, end)
    out = np.zeros(len(classes))
    p = w.p
    first = np.concatenate([p["q"] * np.float32(KEY**-0.5), p["k"], p["v"]], 1)
    near, far = (np.concatenate([p[k], p[k] @ first], 1) for k in ("now", "last"))  # of a class: vector, query, key and value
    top = np.concatenate([p["top"], p["bias"][None]])
    bias = p["far"][_BACK] + _FUTURE
    ones = np.ones(CLASSES, top.dtype)
    held, wide = np.ones((batch * WINDOW, WIDTH + 1), top.dtype), np.empty((batch * WINDOW, CLASSES), top.dtype)
    for a in range(0, len(before), batch):
        part = slice(a, a + batch)
        n = len(before[part])
        x = near.take(before[part].ravel(), 0)
        x += far.take(earlier[part].ravel(), 0)
        cube = x.reshape(n, WINDOW, -1)
        s = cube[..., WIDTH : WIDTH + KEY] @ cube[..., WIDTH + KEY : WIDTH + 2 * KEY].transpose(0, 2, 1)
        s += bias
        np.exp(s, out=s)
        y = s @ cube[..., WIDTH + 2 * KEY :]
        y /= (s @ ones[:WINDOW])[..., None]
        y += cube[..., :WIDTH]
        places = np.flatnonzero(use[part].ravel())  # only these have to be taken to the logits
        y = y.reshape(-1, WIDTH).take(places, 0)
        h = y @ p["in"]
        np.maximum(h, 0, out=h)
        m = len(places)
        np.matmul(h, p["out"], out=held[:m, :WIDTH])
        held[:m, :WIDTH] += y
        logits = np.matmul(held[:m], top, out=wide[:m])
        t, rows = target[part].ravel().take(places), np.arange(m)
        own = logits[rows, t]
        np.exp(logits, out=logits)
        total = logits @ ones
        if not np.isfinite(total).all():  # weights of a size that training does not reach
            full = forward(w, before[part], earlier[part])["logits"].astype(float)[places]
            own, peak = full[rows, t], full.max(1)
            total = np.exp(full - peak[:, None]).sum(1)
            own = own - peak
        out[index[part].ravel().take(places)] = own - np.log(total)
    return out


@dataclass
class Vocabulary:
    """Class of each token id (the last one is the end), and the logarithm of its share within the class."""

    of: np.ndarray
    share: np.ndarray

    @property
    def end(self) -> int:
        return int(self.of[-1])


def own_classes(counts: np.ndarray) -> np.ndarray:
    """The classes of common ids and of the end, which is last; -1 for the others."""
    size = len(counts)
    order = np.lexsort((np.arange(size), -counts))
    of = np.full(size, -1, np.int64)
    head = order[: OWN - 1]
    head = head[head != size - 1]
    of[head] = np.arange(len(head))
    of[size - 1] = OWN - 1
    return of


def make_vocabulary(counts: np.ndarray, ids: np.ndarray, rng: np.random.Generator, smooth: float = 0.1, company: np.ndarray | None = None) -> Vocabulary:
    """Classes from all training counts: own ones for common ids, others by their company, as given or of the successive ids."""
    size = len(counts)
    of = own_classes(counts)
    tail = np.flatnonzero(of < 0)
    slot = np.where(of >= 0, of, OWN)
    if company is None:
        company = np.zeros((size, SIDES))
    else:
        ids = ids[:0]
    if len(ids) > 1:
        np.add.at(company, (ids[1:], slot[ids[:-1]]), 1)
        np.add.at(company, (ids[:-1], OWN + 1 + slot[ids[1:]]), 1)
    groups = CLASSES - OWN
    seen = tail[company[tail].sum(1) >= 5]
    of[tail] = OWN + mix(tail.astype(np.uint64)).astype(np.int64) % groups
    if len(seen) > groups:
        x = np.sqrt(company[seen] / company[seen].sum(1, keepdims=True))
        center = x[rng.choice(len(x), groups, replace=False, p=counts[seen] / counts[seen].sum() if (counts[seen] > 0).sum() > groups else None)]
        for _ in range(12):
            near = np.argmax(x @ center.T - 0.5 * (center**2).sum(1), 1)
            for g in range(groups):
                if (near == g).any():
                    center[g] = x[near == g].mean(0)
        of[seen] = OWN + near
        rare = tail[(company[tail].sum(1) < 5)]
        of[rare] = CLASSES - 1
    weight = counts + smooth
    share = np.log(weight / np.bincount(of, weight, CLASSES)[of])
    return Vocabulary(of, share)


def shares_after(vocabulary: Vocabulary, pairs: np.ndarray, smooth: float = 10.0) -> np.ndarray:
    """Logarithm of each id's share within its class right after each class (rows), from the counts of ids (rows) after classes.

    Added to the counts are smooth tokens, dealt out by the shares that hold after any class.
    """
    out = np.empty((CLASSES, len(vocabulary.of)), np.float32)
    prior = smooth * np.exp(vocabulary.share)
    for c in range(CLASSES):
        n = pairs[:, c]
        out[c] = np.log((n + prior) / (np.bincount(vocabulary.of, n, CLASSES) + smooth)[vocabulary.of])
    return out


def _ids(chunk: Chunk, path: str, end: int) -> tuple[np.ndarray, np.ndarray]:
    """Token ids of lower-cased texts with the end, and each text's bounds."""
    ids, count = word_ids(path, True).encode(chunk)
    total = np.append(0, np.cumsum(count))
    n = total[chunk.word_off[1:]] - total[chunk.word_off[:-1]]
    bounds = np.append(0, np.cumsum(n + 1))
    out = np.full(bounds[-1], end, np.int64)
    fill = np.ones(len(out), bool)
    fill[bounds[1:] - 1] = False
    out[fill] = ids
    return out, bounds


def _merge(h: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values with the sums of their counts."""
    order = np.argsort(h)
    h, n = h[order], n[order]
    first = np.flatnonzero(np.append(True, h[1:] != h[:-1])) if len(h) else np.zeros(0, np.int64)
    return h[first], np.add.reduceat(n, first) if len(first) else n


class Keys:
    """Ascending distinct hashes, and where those with each value of their upper bits start."""

    def __init__(self, keys: np.ndarray) -> None:
        self.keys, bits = keys, min(20, max(1, len(keys).bit_length()))
        self.shift, self.half = 64 - bits, 1 << (bits - 1)
        self.start = np.searchsorted((keys >> self.shift) + self.half, np.arange(2 * self.half)).astype(np.int32)

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Place of each hash among the keys, and whether it is one of them."""
        if not len(self.keys):
            return np.zeros(len(h), np.int32), np.zeros(len(h), bool)
        last = len(self.keys) - 1
        at = np.minimum(self.start[(h >> self.shift) + self.half], last)
        left = np.flatnonzero(self.keys[at] < h)
        while len(left):
            at[left] += 1
            left = left[at[left] <= last]
            left = left[self.keys[at[left]] < h[left]]
        at = np.minimum(at, last)
        return at, self.keys[at] == h


def _prepared(source: DataFrame, path: str, size: int, flush: int = 1_000_000) -> DataFrame:
    """One pass over all texts, as rows of three kinds: 2 a document with its token ids; of training texts, 0 a word's hash
    and 1 a token id with a task's count. Ends are counted; texts go along for the words that scoring looks up."""
    kind_of_id = np.uint16 if size <= 1 << 16 else np.uint32

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, weight, ends = [], [], 0
        tokens = np.zeros(size, np.int64)

        def rows(kind: int, key: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
            m = len(key)
            empty = [pa.nulls(m, t) for t in (pa.int64(), pa.string(), pa.bool_(), pa.binary())]
            return pa.RecordBatch.from_arrays([pa.array(np.full(m, kind, np.int32)), pa.array(key), pa.array(n), *empty], names=NAMES)

        def merged() -> tuple[np.ndarray, np.ndarray]:
            return _merge(np.concatenate(held), np.concatenate(weight))

        for batch in batches:
            training = batch.column(2).to_numpy(zero_copy_only=False).astype(bool)
            for chunk in column_chunks(batch.column(1)):
                learn = training[chunk.row0 : chunk.row1]
                ids, bounds = _ids(chunk, path, size - 1)
                words = chunk.hashes()[learn[chunk.doc]]
                h, n = np.unique(words, return_counts=True)
                held.append(h)
                weight.append(n)
                ends += int(learn.sum())
                tokens += np.bincount(ids[np.repeat(learn, np.diff(bounds))], minlength=size)
                raw = ids.astype(kind_of_id)
                binary = [raw[a:b].tobytes() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                none = pa.nulls(chunk.n, pa.int64())
                doc, text = (batch.column(i).slice(chunk.row0, chunk.n) for i in (0, 1))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(chunk.n, 2, np.int32)), none, none, doc, text, pa.array(learn), pa.array(binary, pa.binary())], names=NAMES)
                if sum(map(len, held)) > 4 * flush:
                    held, weight = ([x] for x in merged())
                    if len(held[0]) > flush:
                        yield rows(0, held[0].view(np.int64), weight[0])
                        held, weight = [], []
        if ends:
            held.append(END_WORD)
            weight.append(np.array([ends]))
            h, n = merged()
            yield rows(0, h.view(np.int64), n)
            some = np.flatnonzero(tokens)
            yield rows(1, some, tokens[some])

    kinds = "kind int, key bigint, n bigint, doc_id bigint, text string, train boolean, ids binary"
    return written(source.mapInArrow(run, kinds).withColumn("row", F.monotonically_increasing_id()), "lm")


NAMES = ["kind", "key", "n", "doc_id", "text", "train", "ids"]


def _bytes_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a column of byte strings one after another, and the bounds of each."""
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    off = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    return np.frombuffer(column.buffers()[2] or b"", np.uint8)[off[0] : off[-1]], off - off[0]


def _ids_of(column: pa.Array, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Token ids of a column of byte strings one after another, and the bounds of each."""
    width = 2 if size <= 1 << 16 else 4
    data, off = _bytes_of(column)
    return data.view(np.uint16 if width == 2 else np.uint32).astype(np.int64), off // width


class _Blocks:
    """Counts of size ids by wide columns that a task sends as one row for each of BLOCKS blocks of ids, with the places and
    numbers of those that are not 0; Spark deals the blocks out to be added up."""

    KINDS = "block int, at binary, n binary"

    def __init__(self, size: int, wide: int, flush: int) -> None:
        self.per, self.wide, self.flush = -(-size // BLOCKS), wide, flush
        self.total = np.zeros(BLOCKS * self.per * wide, np.int64)
        i = np.arange(size)
        self.base = (i % BLOCKS * self.per + i // BLOCKS) * wide
        self.held: list[np.ndarray] = []
        self.n = 0

    def add(self, ids: np.ndarray, column: np.ndarray) -> None:
        self.held.append(self.base[ids] + column)
        self.n += len(ids)
        if self.n > self.flush:
            self.settle()

    def settle(self) -> np.ndarray:
        if self.n:
            self.total += np.bincount(np.concatenate(self.held), minlength=len(self.total))
            self.held, self.n = [], 0
        return self.total.reshape(BLOCKS, -1)

    @staticmethod
    def rows(blocks: Iterator[tuple[int, np.ndarray]]) -> Iterator[list[pa.Array]]:
        for block, total in blocks:
            at = np.flatnonzero(total)
            if len(at):
                data = [[at.astype(np.uint32).tobytes()], [total[at].astype(np.int64).tobytes()]]
                yield [pa.array([block], pa.int32()), *(pa.array(x, pa.binary()) for x in data)]

    @staticmethod
    def summed(sent: DataFrame, size: int, wide: int) -> np.ndarray:
        """The sum of all tasks' counts, ids by columns."""
        per = -(-size // BLOCKS)

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, np.ndarray] = {}
            for batch in batches:
                for block, at, n in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    sums.setdefault(block, np.zeros(per * wide, np.int64))[np.frombuffer(at, np.uint32)] += np.frombuffer(n, np.int64)
            for row in _Blocks.rows(iter(sums.items())):
                yield pa.RecordBatch.from_arrays(row, names=["block", "at", "n"])

        out = np.zeros((BLOCKS, per * wide), np.int64)
        for r in sent.select("block", "at", "n").repartition("block").mapInArrow(add, _Blocks.KINDS).toLocalIterator():  # at most a row a block
            out[r.block, np.frombuffer(r.at, np.uint32)] = np.frombuffer(r.n, np.int64)
        i = np.arange(size)
        return out.reshape(BLOCKS, per, wide)[i % BLOCKS, i // BLOCKS]


def _company(train: DataFrame, counts: np.ndarray, flush: int = 2_000_000) -> np.ndarray:
    """How often each id without an own class comes right after, and right before, each own class or any other, in all texts.

    The end comes before the first id of a text.
    """
    size = len(counts)
    sent = train.sparkSession.sparkContext.broadcast(own_classes(counts))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = sent.value
        slot = np.where(own >= 0, own, OWN)
        blocks = _Blocks(size, SIDES, flush)
        for batch in batches:
            for a in range(0, batch.num_rows, 1024):
                ids, _ = _ids_of(batch.column(0).slice(a, 1024), size)  # each text closes with an end, so that ends part them
                s = slot[ids]
                at = np.flatnonzero(s == OWN)
                blocks.add(ids[at], np.where(at > 0, s[at - 1], OWN - 1))
                blocks.add(ids[at], OWN + 1 + s[at + 1])
        for row in _Blocks.rows(enumerate(blocks.settle())):
            yield pa.RecordBatch.from_arrays(row, names=["block", "at", "n"])

    return _Blocks.summed(train.select("ids").mapInArrow(count, _Blocks.KINDS), size, SIDES)


def _followed(train: DataFrame, vocabulary: Vocabulary, every: int, flush: int = 2_000_000) -> DataFrame:
    """One pass over all training texts, once classes are known: blocks of counts of ids without an own class by the class
    before them, and, with no block, each text's key and classes, to refine on one in every of its windows."""
    sent = train.sparkSession.sparkContext.broadcast(vocabulary)
    names = ["block", "at", "n", "key", "classes", "every"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = sent.value
        size = len(vocabulary.of)
        blocks = _Blocks(size, CLASSES, flush)
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                ids, bounds = _ids_of(batch.column(0).slice(a, 256), size)
                key = batch.column(1).slice(a, 256).to_numpy()
                classes = vocabulary.of[ids]
                at = np.flatnonzero(classes >= OWN)
                blocks.add(ids[at], np.where(at > 0, classes[at - 1], vocabulary.end))
                m = len(key)
                line = pa.Array.from_buffers(pa.binary(), m, [None, pa.py_buffer(bounds.astype(np.int32)), pa.py_buffer(classes.astype(np.uint8))])
                none = [pa.nulls(m, t) for t in (pa.int32(), pa.binary(), pa.binary())]
                yield pa.RecordBatch.from_arrays([*none, pa.array(key), line, pa.array(np.full(m, every, np.int32))], names=names)
        for row in _Blocks.rows(enumerate(blocks.settle())):
            yield pa.RecordBatch.from_arrays([*row, *(pa.nulls(1, t) for t in (pa.int64(), pa.binary(), pa.int32()))], names=names)

    return train.select("ids", "key").mapInArrow(run, _Blocks.KINDS + ", key bigint, classes binary, every int")


def _fit(ids: np.ndarray, bounds: np.ndarray, counts: np.ndarray, company: np.ndarray, steps: int, seed: int) -> tuple[Vocabulary, Weights]:
    """Vocabulary from all counts, and weights from the token ids of a sample of texts."""
    rng = np.random.default_rng(seed)
    vocabulary = make_vocabulary(counts, ids, rng, company=company)
    w = Weights.fresh(rng)
    prior = np.bincount(vocabulary.of, counts + 0.1, CLASSES)
    w.p["bias"] = np.log(np.maximum(prior, 1e-6) / prior.sum()).astype(np.float32)
    if len(ids):
        before, earlier, target, use, _ = windows_of(vocabulary.of[ids], bounds, vocabulary.end)
        fit = Fitter(w, 0.01)
        for s in range(steps):
            pick = rng.integers(0, len(before), 64)
            fit.step(before[pick], earlier[pick], target[pick], use[pick], 0.01 * (1 - s / steps) + 0.0003)
    return vocabulary, w


def _refined(lines: DataFrame, texts: int, w: Weights, group: int = GROUP) -> Weights:
    """Weights after each group of texts (key, classes, every) went on with its windows, averaged by the groups' numbers of windows.

    The group that a text goes to, and its order there, come from a hash of it alone. The windows of about POOL tokens of successive
    texts are mixed, always alike, so that a step is not on one text.
    """
    sent = lines.sparkSession.sparkContext.broadcast(w)
    groups = max(1, -(-texts // group))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start = sent.value
        x, done, own, now, last = np.zeros(len(start.flat())), 0, 0, None, None
        fit = Fitter(start.of_flat(start.flat()), 0.0005)
        pool: list[tuple[int, bytes, int]] = []
        tokens = 0
        held = np.zeros((0, 4, WINDOW), np.uint8)

        def steps(all_of_them: bool) -> None:
            nonlocal held, own, pool, tokens
            if pool:
                keys, raw, every = zip(*pool, strict=True)
                bounds = np.append(0, np.cumsum([len(r) for r in raw]))
                parts = windows_of(np.frombuffer(b"".join(raw), np.uint8), bounds, OWN - 1, every[0], np.array(keys))[:4]
                mixed = np.random.default_rng(len(parts[0])).permutation(len(parts[0]))
                held = np.concatenate([held, np.stack([p.astype(np.uint8) for p in parts], 1)[mixed]])
                pool, tokens = [], 0
            cut = len(held) if all_of_them else len(held) // 64 * 64
            for k in range(0, cut, 64):
                before, earlier, target, use = held[k : min(k + 64, cut)].transpose(1, 0, 2)
                fit.step(before, earlier, target, use.astype(bool))
            own, held = own + cut, held[cut:]

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if row == last:  # a row that repeats
                    continue
                last = row
                if row[0] != now and now is not None:
                    steps(True)
                    x, done, own = x + fit.w.flat() * float(own), done + own, 0
                    fit = Fitter(start.of_flat(start.flat()), 0.0005)
                now = row[0]
                pool.append(row[1:])
                tokens += len(row[2])
                if tokens > POOL:
                    steps(False)
        steps(True)
        x, done = x + fit.w.flat() * float(own), done + own
        if done:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(x), dtype=np.int32)), pa.array(x), pa.array(np.full(len(x), float(done)))], names=["at", "x", "n"])

    dealt = lines.select(F.pmod(F.xxhash64("key"), F.lit(groups)).alias("g"), "key", "classes", "every")
    dealt = dealt.repartition(min(groups, PARTS), "g").sortWithinPartitions("g", "key", "classes")
    mean = dealt.mapInArrow(run, "at int, x double, n double").groupBy("at").agg((F.sum("x") / F.sum("n")).alias("x")).toArrow()
    if not len(mean):
        return w
    flat = np.zeros(len(mean))
    flat[mean["at"].to_numpy()] = mean["x"].to_numpy()
    return w.of_flat(flat)


def language_model_scores(
    docs: DataFrame, is_training: Column, path: str, *, fit_tokens: int = 1_000_000, steps: int = 2500, max_table: int = 500_000, refine_every: int = 1, seed: int = 17
) -> DataFrame:
    """Score documents (doc_id, text); is_training marks, by doc_id, those to learn from. path: a tokenizer file.

    Returns doc_id, n_tokens (words and the end), n_known (words seen in training), train_tokens, base_score
    (logarithm by counts of words, add-one) and score (logarithm by the attention model), both to base ten.
    """
    spark = docs.sparkSession
    source = has_columns(docs, "doc_id", "text").withColumn("_train", F.coalesce(is_training, F.lit(False)))
    size = word_ids(path, True).tokenizer.get_vocab_size(True) + 1
    table = _prepared(source, path, size)
    texts = table.where("kind = 2")
    train = texts.where("train").withColumn("key", F.xxhash64("doc_id", "ids"))
    sums = table.where("kind < 2").groupBy("kind", "key").agg(F.sum("n").alias("n")).checkpoint()
    words = sums.where("kind = 0").select(F.col("key").alias("h"), "n")
    totals = words.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count("*").alias("v")).first()
    log_total = float(np.log10(totals.n + totals.v + 1))
    tokens = sums.where("kind = 1").select("key", "n").toArrow()  # at most one row a token id
    by_id = np.zeros(size, np.int64)
    by_id[tokens["key"].to_numpy()] = tokens["n"].to_numpy()
    mean = max(1.0, by_id.sum() / max(by_id[-1], 1))
    rows = max(16, int(fit_tokens / mean))
    share = min(1.0, 2.0 * rows / max(int(by_id[-1]), 1))
    near = F.pmod(F.col("key"), F.lit(1 << 20)) <= int(share * (1 << 20))
    sample = train.where(near).select("ids", F.xxhash64("key").alias("h")).orderBy("h", "ids").limit(rows).toArrow()["ids"].combine_chunks()
    ids, bounds = _ids_of(sample, size) if len(sample) else (np.zeros(0, np.int64), np.zeros(1, np.int64))
    vocabulary, w = _fit(ids, bounds, by_id, _company(train, by_id), steps, seed)
    followed = written(_followed(train, vocabulary, refine_every), "followed")
    after = shares_after(vocabulary, _Blocks.summed(followed.where("block is not null"), size, CLASSES))
    w = _refined(followed.where("block is null"), int(by_id[-1]), w)

    bound = 2
    for r in sorted(words.groupBy(F.floor(F.log2("n")).alias("k")).count().collect(), key=lambda r: -r.k):
        max_table -= r["count"]
        if max_table < 0:
            bound = max(bound, 2 ** (int(r.k) + 1))
            break
    common = words.where(F.col("n") >= bound).orderBy("h").toArrow()
    sent = spark.sparkContext.broadcast((Keys(common["h"].to_numpy()), np.log10(common["n"].to_numpy() + 1.0), vocabulary, after, w))

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, logs, vocabulary, after, w = sent.value
        for batch in batches:
            for chunk in column_chunks(batch.column(1)):
                h = chunk.hashes().view(np.int64)
                at, known = keys.find(h)
                gain = np.append(0.0, np.cumsum(np.where(known, logs[at], 0.0) if len(logs) else np.zeros(len(h))))
                cut = np.append(0, np.cumsum(known))
                miss = np.append(0, np.cumsum(~known)).astype(np.int32)
                a, b = chunk.word_off[:-1], chunk.word_off[1:]
                ids, bounds = _ids_of(batch.column(2).slice(chunk.row0, chunk.n), len(vocabulary.of))
                classes = vocabulary.of[ids]
                chance = log_chances(w, classes, bounds, vocabulary.end) + after[np.append(vocabulary.end, classes[:-1]), ids]
                rest = pa.ListArray.from_arrays(pa.array(miss[np.append(a, b[-1:])]), pa.array(h[~known]))
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(chunk.row0, chunk.n),
                        batch.column(3).slice(chunk.row0, chunk.n),
                        pa.array(chunk.n_words + 1),
                        pa.array(cut[b] - cut[a]),
                        pa.array(gain[b] - gain[a]),
                        rest,
                        pa.array(np.add.reduceat(chance, bounds[:-1]) / np.log(10)),
                    ],
                    names=["doc_id", "row", "n_tokens", "known", "gain", "rest", "score"],
                )

    scored = texts.select("doc_id", "text", "ids", "row").mapInArrow(score, "doc_id bigint, row bigint, n_tokens bigint, known bigint, gain double, rest array<bigint>, score double")
    scored = written(scored, "scored")
    rare = scored.select("row", F.explode("rest").alias("h")).groupBy("row", "h").agg(F.count("*").alias("times"))
    found = (
        rare.join(words.where(F.col("n") < bound), "h")
        .groupBy("row")
        .agg(F.sum("times").alias("more"), F.sum(F.col("times") * F.log10(F.col("n") + 1.0)).alias("plus"))
    )
    ends = int(by_id[-1])
    end_log, end_known = float(np.log10(ends + 1.0)), int(ends > 0)
    return scored.join(found, "row", "left").select(
        "doc_id",
        "n_tokens",
        (F.col("known") + F.coalesce("more", F.lit(0)) + end_known).cast("bigint").alias("n_known"),
        F.lit(int(totals.n)).cast("bigint").alias("train_tokens"),
        (F.col("gain") + F.coalesce("plus", F.lit(0.0)) + end_log - F.col("n_tokens") * log_total).alias("base_score"),
        "score",
    )
