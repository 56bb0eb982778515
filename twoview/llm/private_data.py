"""Personal data: fixed rules, and identifiers found by bootstrapped context patterns.

The rules (email, ip, card, phone) give sure spans. Each of them, however many words it has, is a seed with the
words around it as its context. Every word of SHORT characters or more that has a digit, an inner mark
(hyphen and apostrophe aside) or an inner capital is a candidate, so that plain words are none. The words around a
seed or candidate, its leading letters and its first characters are its patterns. Spark scores the graph of
patterns and candidates in rounds: a pattern is as good as the mean score of the distinct candidates it extracts, a
candidate as good as its good patterns together, and seeds stay at one. Patterns that end with high
confidence and enough distinct candidates mark further spans, of kind "id".

Patterns and candidates are 63-bit hashes of whole words, never cut. Texts are read twice, once to learn and once to
mark, so that spans meet their texts without a join and every row, with or without an id, gets its own. The learned
patterns are sent out in parts of at most PART, one after another.

Cases: a null text is an empty one and has no spans; masked, it stays null. Repeated rows get equal spans. Spans count
code points, ends exclusive. Found spans never replace rule spans: a word that overlaps a rule span is no candidate.
An empty table gives an empty result. Other columns are left out of account; masking keeps them.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import has_columns
from twoview.llm.text import Chunk, column_chunks, mix, span_hashes

KINDS = ("email", "ip", "card", "phone", "id")
SHORT = 4
PART = 1_000_000
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")


def _lookup(chars: str) -> np.ndarray:
    table = np.zeros(129, bool)
    table[[ord(c) for c in chars]] = True
    return table


_ALNUM = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
_LOCAL, _HOST, _NUMBER, _DIAL = (_lookup(x) for x in (_ALNUM + "._%+-", _ALNUM + ".-", "0123456789.", "0123456789 ().-"))
_LETTER, _UPPER, _JOINT = (_lookup(x) for x in (_ALNUM[10:], _ALNUM[10:36], "=:_-"))
_WORDY = _lookup(_ALNUM)
_LETTER[128] = _WORDY[128] = True  # characters beyond ASCII count as letters
_PLAIN = _LETTER | _lookup("-'")
_EDGE = np.uint64(0x5E)
NONE = -1


def luhn(digits: str) -> bool:
    """The checksum of card numbers."""
    odd = sum(map(int, digits[-1::-2]))
    return (odd + sum(sum(divmod(2 * int(d), 10)) for d in digits[-2::-2])) % 10 == 0


def _runs(mask: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the runs of True; a text's edge ends a run."""
    flags = np.zeros(len(mask) + 1, bool)
    flags[1:-1] = mask[1:] != mask[:-1]
    flags[off] = True
    at = np.flatnonzero(flags)
    if len(at) < 2:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    inside = mask[at[:-1]]
    return at[:-1][inside], at[1:][inside]


def _emails(chunk: Chunk, cp: np.ndarray) -> list[tuple[int, int, int]]:
    ats = np.flatnonzero(cp == 64)
    if not len(ats):
        return []
    starts, ends = _runs(_LOCAL[cp], chunk.off)
    left = np.searchsorted(ends, ats)
    hosts, host_ends = _runs(_HOST[cp], chunk.off)
    right = np.searchsorted(hosts, ats + 1)
    out, last = [], 0
    for k, i, j in zip(ats.tolist(), left.tolist(), right.tolist(), strict=True):
        if i >= len(ends) or ends[i] != k or j >= len(hosts) or hosts[j] != k + 1:
            continue
        a = max(int(starts[i]), last)
        doc = int(np.searchsorted(chunk.off, k, "right")) - 1
        if a < k and a >= chunk.off[doc] and k + 1 < chunk.off[doc + 1] and (m := _DOMAIN.match(chunk.text(k + 1, int(host_ends[j])))):
            last = k + 1 + m.end()
            out.append((0, a, last))
    return out


def _addresses(chunk: Chunk, cp: np.ndarray) -> list[tuple[int, int, int]]:
    starts, ends = _runs(_NUMBER[cp], chunk.off)
    dots = np.append(0, np.cumsum(cp == 46))
    out = []
    for i in np.flatnonzero(dots[ends] - dots[starts] >= 3).tolist():
        parts = chunk.text(int(starts[i]), int(ends[i])).split(".")
        at = [int(starts[i])]
        for p in parts:
            at.append(at[-1] + len(p) + 1)
        k = 0
        while k + 3 < len(parts):
            if all(parts[k : k + 4]):
                if all(len(p.lstrip("0")) <= 3 and int(p[-3:]) <= 255 for p in parts[k : k + 4]):
                    out.append((1, at[k], at[k + 4] - 1))
                k += 4
            else:
                k += 1
    return out


def _cards(chunk: Chunk, digit_runs: tuple[np.ndarray, np.ndarray]) -> list[tuple[int, int, int]]:
    starts, ends = digit_runs
    if not len(starts):
        return []
    gap = chunk.cp[np.minimum(ends[:-1], len(chunk.cp) - 1)]
    doc = np.searchsorted(chunk.off, starts, "right")
    joined = (starts[1:] - ends[:-1] == 1) & ((gap == 32) | (gap == 45)) & (doc[1:] == doc[:-1])
    first = np.flatnonzero(np.append(True, ~joined))
    n_digits = np.add.reduceat(ends - starts, first)
    last = np.append(first[1:], len(starts)) - 1
    out = []
    for g in np.flatnonzero((n_digits >= 14) & (n_digits <= 19)).tolist():
        a, b = int(starts[first[g]]), int(ends[last[g]])
        if luhn(re.sub("[^0-9]", "", chunk.text(a, b))):
            out.append((2, a, b))
    return out


def _phones(chunk: Chunk, cp: np.ndarray) -> list[tuple[int, int, int]]:
    plus = np.flatnonzero(cp[:-1] == 43)
    plus = plus[(cp[plus + 1] - np.uint32(48)) < 10]
    if not len(plus):
        return []
    starts, ends = _runs(_DIAL[cp], chunk.off)
    out = []
    for k in plus.tolist():
        i = int(np.searchsorted(starts, k + 1))
        if i >= len(starts) or starts[i] != k + 1:
            continue
        t = chunk.text(k, int(ends[i])).rstrip(" ().-")
        if len(t) >= 4 and 10 <= sum(c.isdigit() for c in t) <= 15:
            out.append((3, k, k + len(t)))
    return out


def _same_doc(chunk: Chunk, spans: list[tuple[int, int, int]]) -> list[tuple[int, int, int, int]]:
    if not spans:
        return []
    docs = np.searchsorted(chunk.off, [s for _, s, _ in spans], "right") - 1
    return sorted((int(d), s, k, e) for d, (k, s, e) in zip(docs, spans, strict=True))


def rule_spans(chunk: Chunk) -> list[tuple[int, int, int, int]]:
    """All rule spans as (text, start, kind, end) within the chunk, in order."""
    cp = np.minimum(chunk.cp, 128)
    digits = (cp - np.uint32(48)) < 10
    spans = _emails(chunk, cp)
    if digits.any():
        spans += _addresses(chunk, cp) + _cards(chunk, _runs(digits, chunk.off)) + _phones(chunk, cp)
    return _same_doc(chunk, spans)


@dataclass
class Units:
    """Seeds and candidates of a chunk: text, start and end of each, whether it is a seed, its hash, and the hashes of its patterns by row."""

    doc: np.ndarray
    start: np.ndarray
    end: np.ndarray
    seed: np.ndarray
    inst: np.ndarray
    pats: np.ndarray


def _tagged(h: np.ndarray, tag: int) -> np.ndarray:
    return mix(h ^ np.uint64(tag * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)) >> np.uint64(1)


def _cores(chunk: Chunk) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Each word without the marks at its edges, as start, end and hash; a word of marks alone is empty and has hash 0."""
    cp = np.minimum(chunk.cp, 128)
    at = np.flatnonzero(_WORDY[cp])
    a, b = np.searchsorted(at, chunk.starts), np.searchsorted(at, chunk.ends)
    some = b > a
    starts, ends = chunk.starts.copy(), chunk.starts.copy()
    starts[some], ends[some] = at[a[some]], at[b[some] - 1] + 1
    h = np.zeros(len(starts), np.uint64)
    if some.any():
        edge = np.zeros(len(chunk.cp) + 1, np.int8)
        edge[starts[some]] += 1
        edge[ends[some]] -= 1
        h[some] = span_hashes(chunk.lower, starts[some], ends[some], np.cumsum(edge[:-1]) > 0)
    return starts, ends, h


def units(chunk: Chunk, spans: list[tuple[int, int, int, int]]) -> Units:
    """Seeds, which are the rule spans, and candidates with their patterns.

    Patterns: the word before, the two before, the word after, both sides, the leading letters with a mark that
    follows, the first characters of a long one. Beyond a text's edge stands one and the same word.
    """
    starts, ends, h = _cores(chunk)
    n = len(starts)
    total = np.append(np.uint64(0), np.cumsum(mix(h.copy())))
    cp, size = np.minimum(chunk.cp, 128), ends - starts

    def inside(flags: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        upto = np.append(0, np.cumsum(flags))
        return upto[np.maximum(b, a)] - upto[a]

    upper = _UPPER[cp]
    odd = (size >= SHORT) & ((inside(~_PLAIN[cp], starts, ends) > 0) | (inside(upper, np.minimum(starts + 1, ends), ends) > 0))
    first = np.array([int(np.searchsorted(chunk.ends, s, "right")) for _, s, _, _ in spans], np.int64)
    last = np.array([int(np.searchsorted(chunk.starts, e, "left")) - 1 for _, _, _, e in spans], np.int64)
    for a, b in zip(first.tolist(), last.tolist(), strict=True):
        odd[a : b + 1] = False
    own = np.flatnonzero(odd)
    lo, hi = np.concatenate([first, own]), np.concatenate([last, own])
    seed = np.arange(len(lo)) < len(first)
    if not len(lo):
        none = np.zeros(0, np.int64)
        return Units(none, none, none, seed, none, np.zeros((0, 6), np.int64))
    doc = chunk.doc[lo].astype(np.int64)

    def near(i: np.ndarray) -> np.ndarray:
        ok = (i >= chunk.word_off[doc]) & (i < chunk.word_off[doc + 1])
        return np.where(ok, h[np.clip(i, 0, n - 1)], _EDGE)

    before, earlier, after = near(lo - 1), near(lo - 2), near(hi + 1)
    letters = np.append(np.flatnonzero(~_LETTER[cp]), len(cp))
    head = np.minimum(letters[np.searchsorted(letters, starts[lo])], ends[lo])
    mark = (head < ends[lo]) & (head > starts[lo])
    mark[mark] = _JOINT[cp[head[mark]]]
    inst = mix(total[hi + 1] - total[lo])
    heads, fours = _some_hash(chunk.lower, starts[lo], head + mark), _some_hash(chunk.lower, starts[lo], np.minimum(starts[lo] + 4, ends[lo]))
    k = np.uint64(0xD6E8FEB86659FD93)
    pats = np.stack([_tagged(before, 1), _tagged(before + earlier * k, 2), _tagged(after.copy(), 3), _tagged(before + after * k, 4), _tagged(heads, 5), _tagged(fours, 6)], 1)
    pats = pats.view(np.int64)
    pats[head - starts[lo] < 2, 4] = NONE
    pats[ends[lo] - starts[lo] < 8, 5] = NONE
    s, e = starts[lo].copy(), ends[lo].copy()
    s[seed], e[seed] = [x for _, x, _, _ in spans], [x for _, _, _, x in spans]
    return Units(doc, s - chunk.off[doc], e - chunk.off[doc], seed, (inst >> np.uint64(1)).view(np.int64), pats)


def _some_hash(cp: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Hashes of spans of any order, by their characters."""
    out, lens = np.zeros(len(a), np.uint64), b - a
    for i in range(int(lens.max(initial=0))):
        on = np.flatnonzero(lens > i)
        out[on] = mix(out[on] * np.uint64(0x9E3779B97F4A7C15) + cp[a[on] + i].astype(np.uint64) + np.uint64(1))
    return out


def edges(chunk: Chunk) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (pattern, candidate, whether a seed) of a chunk."""
    u = units(chunk, rule_spans(chunk))
    pat, inst, seed = u.pats.ravel(), np.repeat(u.inst, 6), np.repeat(u.seed, 6)
    pat, inst, seed = (x[pat != NONE] for x in (pat, inst, seed))
    order = np.lexsort((~seed, inst, pat))
    pat, inst, seed = pat[order], inst[order], seed[order]
    new = np.append(True, (pat[1:] != pat[:-1]) | (inst[1:] != inst[:-1])) if len(pat) else np.zeros(0, bool)
    return pat[new], inst[new], seed[new]


def pattern_scores(edges: DataFrame, rounds: int, min_confidence: float, min_support: int) -> DataFrame:
    """Patterns (pat, confidence, support) that end good, of distinct edges (pat, inst, seed).

    Rounds alternate between the two sides of the graph. A pattern needs min_support distinct candidates that
    score well, and the mean of min_confidence over all that it extracts.
    """
    insts = edges.groupBy("inst").agg(F.max(F.col("seed").cast("double")).alias("score"))
    good = None
    for r in range(rounds):
        scored = edges.join(insts, "inst")
        good = (
            scored.groupBy("pat")
            .agg(F.avg("score").alias("confidence"), F.count_if(F.col("score") >= min_confidence).alias("support"))
            .where((F.col("confidence") >= min_confidence) & (F.col("support") >= min_support))
        )
        good = good.checkpoint()
        if r + 1 < rounds:
            gained = edges.join(good, "pat").groupBy("inst").agg((1 - F.exp(F.sum(F.log(F.greatest(1 - F.col("confidence"), F.lit(1e-6)))))).alias("gain"))
            insts = (
                insts.join(gained, "inst", "left")
                .select("inst", F.greatest("score", F.coalesce("gain", F.lit(0.0))).alias("score"))
                .checkpoint()
            )
    return good


def learn_patterns(docs: DataFrame, *, rounds: int = 3, min_confidence: float = 0.9, min_support: int = 5, part: int = PART) -> list[np.ndarray]:
    """The good patterns of all texts (text), as sorted arrays of at most part hashes each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in column_chunks(batch.column(0)):
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in edges(chunk)], names=["pat", "inst", "seed"])

    found = has_columns(docs, "text").mapInArrow(run, "pat bigint, inst bigint, seed boolean")
    graph = found.groupBy("pat", "inst").agg(F.max("seed").alias("seed")).checkpoint()
    good = pattern_scores(graph, rounds, min_confidence, min_support).select("pat").checkpoint()
    parts = max(1, -(-good.count() // part))
    if parts == 1:
        return [np.sort(good.toArrow()["pat"].to_numpy())]
    return [np.sort(good.where(F.pmod(F.xxhash64("pat"), F.lit(parts)) == p).toArrow()["pat"].to_numpy()) for p in range(parts)]


def _found(chunk: Chunk, spans: list[tuple[int, int, int, int]], patterns: list[np.ndarray]) -> list[tuple[int, int, int, int]]:
    """Spans of kind id, as (text, start, kind, end) within the text."""
    u = units(chunk, spans)
    good = np.zeros(len(u.doc), bool)
    for known in patterns:
        if len(known) and len(u.doc):
            at = np.minimum(np.searchsorted(known, u.pats), len(known) - 1)
            good |= (known[at] == u.pats).any(1)
    good &= ~u.seed
    return list(zip(u.doc[good].tolist(), u.start[good].tolist(), [4] * int(good.sum()), u.end[good].tolist(), strict=True))


def scan(chunk: Chunk, patterns: list[np.ndarray]) -> tuple[np.ndarray, list[list[tuple[int, int, int]]]]:
    """Counts of each kind by text, and all spans of each text as (start, kind, end) in order."""
    rules = rule_spans(chunk)
    counts = np.zeros((5, chunk.n), np.int64)
    texts: list[list[tuple[int, int, int]]] = [[] for _ in range(chunk.n)]
    for d, s, k, e in rules:
        texts[d].append((s - int(chunk.off[d]), k, e - int(chunk.off[d])))
    for d, s, k, e in _found(chunk, rules, patterns):
        texts[d].append((s, k, e))
    for d, spans in enumerate(texts):
        if spans:
            spans.sort()
            for _, k, _ in spans:
                counts[k, d] += 1
    return counts, texts


def written_spans(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


OUT = "n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, n_id bigint, base string, base_sha256 string, spans string"


def private_data(docs: DataFrame, **options) -> DataFrame:
    """Find personal data in documents (doc_id, text); options are those of learn_patterns.

    Returns doc_id, the spans' counts, base (rule spans as kind:start:end, comma-joined), base_sha256 and spans (rule
    and found spans by start, then kind), one row for each row of docs.
    """
    source = has_columns(docs, "doc_id", "text")
    sent = docs.sparkSession.sparkContext.broadcast(learn_patterns(source, **options))
    empty = hashlib.sha256(b"").hexdigest()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in column_chunks(batch.column(1)):
                counts, texts = scan(chunk, sent.value)
                base = [written_spans([x for x in t if x[1] < 4]) if t else "" for t in texts]
                sha = [hashlib.sha256(b.encode()).hexdigest() if b else empty for b in base]
                whole = [written_spans(t) if t else "" for t in texts]
                columns = [*map(pa.array, counts), *(pa.array(x, pa.string()) for x in (base, sha, whole))]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(chunk.row0, chunk.n), *columns], names=["doc_id", *(c.split()[0] for c in OUT.split(", "))])

    kind = source.schema["doc_id"].dataType.simpleString()
    return source.mapInArrow(run, f"doc_id {kind}, {OUT}")


def mask(text: str, spans: list[tuple[int, int, int]]) -> str:
    """text with each span replaced by its kind in angle brackets; where spans overlap, the first stands for all."""
    out, at = [], 0
    for s, k, e in spans:
        if s >= at:
            out += [text[at:s], f"<{KINDS[k]}>"]
            at = e
    return "".join([*out, text[at:]])


def masked(docs: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """docs with the personal data of each row's text replaced by its kind; all rows and columns stay."""
    at = docs.columns.index(text_col)
    sent = docs.sparkSession.sparkContext.broadcast(learn_patterns(docs.select(F.col(f"`{text_col}`").alias("text")), **options))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            changed, new = np.zeros(batch.num_rows, bool), []
            for chunk in column_chunks(batch.column(at)):
                for d, spans in enumerate(scan(chunk, sent.value)[1]):
                    if spans:
                        changed[chunk.row0 + d] = True
                        new.append(mask(chunk.text(int(chunk.off[d]), int(chunk.off[d + 1])), spans))
            if new:
                column = pc.replace_with_mask(batch.column(at), pa.array(changed), pa.array(new, batch.column(at).type))
                batch = pa.RecordBatch.from_arrays([column if i == at else c for i, c in enumerate(batch.columns)], schema=batch.schema)
            yield batch

    return docs.mapInArrow(run, docs.schema)
