"""Mixing sources to target weights by fair scheduling, in DataFrame operations only.

Each source's rows come in blocks. With weights given, or more sources than a period has slots, or no period, each block's
slot follows from its number and the exact weights: sources are joined two by two, lightest first, and where
a joined pair has had k blocks, its first part has had its share of k, rounded to the nearest. So the
distance from the asked share has a bound for each source, under two blocks, at every slot however many there are.

Otherwise weights, the root of row counts, are rounded to whole parts of a period, at least one each, as the SQL form has
it: block i (from 1) of a source of weight w is released at the floor of (i - 1) / w and due by the ceiling of i / w, and
in each slot the released block that is due first goes next. The target is the rounded share, and each source is less
than one block from that one; from the root itself it moves off by the rounding, in proportion to the slots.

All rows stay. A source that runs out leaves its slots empty and the others keep their order.

Cases: rows without a source are a source of their own. Equal ids follow each other in any order. Sources that
weights leave out or give 0 follow after all others. An empty table gives an empty result. Other columns ride along;
those named block, slot, place or target are replaced.
"""

from __future__ import annotations

import heapq
from fractions import Fraction
from math import lcm

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twoview.llm.base import ranked

PERIOD = 1000
BLOCK_ROWS = 8
MOST = 10**18


def quotas(weights: dict[str | None, float], period: int = PERIOD) -> list[tuple[str | None, int]]:
    """Slots of a period for each source, at least one: floors first, then by largest remainder, then by name. Largest first."""
    if len(weights) > period:
        raise ValueError(f"{len(weights)} sources don't fit a period of {period} slots")
    total = sum(weights.values())
    names = sorted(weights, key=lambda s: (s is not None, s))
    spare = period - len(names)
    exact = {s: weights[s] / total * spare for s in names}
    whole = {s: int(exact[s]) for s in names}
    for s in sorted(names, key=lambda s: (whole[s] - exact[s], s is not None, s))[: spare - sum(whole.values())]:
        whole[s] += 1
    return sorted(((s, whole[s] + 1) for s in names), key=lambda x: (-x[1], x[0] is not None, x[0]))


def fair_schedule(parts: list[int]) -> list[tuple[int, int]]:
    """For each slot of a period, the sum of parts, which source goes (earliest deadline of those released) and its how-manieth block."""
    period, done, out = sum(parts), [0] * len(parts), []
    for slot in range(period):
        ready = [(-(-(done[i] + 1) * period // q), i) for i, q in enumerate(parts) if done[i] * period // q <= slot]
        due, i = min(ready)
        if due <= slot:
            raise RuntimeError("a block is late")
        out.append((i, done[i]))
        done[i] += 1
    return out


def whole_weights(weights: dict[str | None, float]) -> dict[str | None, int]:
    """Whole numbers in the exact ratio of the weights; where their sum is over MOST, of a share to its nearest part of MOST."""
    exact = {s: Fraction(w) for s, w in weights.items()}
    if any(w < 0 for w in exact.values()) or not any(exact.values()):
        raise ValueError("weights are to be at least 0, and one more than that")
    scale = lcm(*(w.denominator for w in exact.values()))
    whole = {s: int(w * scale) for s, w in exact.items()}
    total = sum(whole.values())
    if total <= MOST:
        return whole
    return {s: max(1, round(Fraction(w * MOST, total))) if w else 0 for s, w in whole.items()}


def paths(whole: dict[str | None, int]) -> dict[str | None, list[tuple[int, int, int]]]:
    """For each source of weight its steps up the tree of joined pairs: the pair's weight, an addend, and twice its own weight."""
    names = sorted((s for s in whole if whole[s]), key=lambda s: (whole[s], s is not None, s))
    heap = [(whole[s], i) for i, s in enumerate(names)]
    up: dict[int, tuple[int, tuple[int, int, int]]] = {}
    node = len(names)
    while len(heap) > 1:
        (light, a), (heavy, b) = heapq.heappop(heap), heapq.heappop(heap)
        up[b] = (node, (light + heavy, 2 * heavy - 1, 2 * heavy))
        up[a] = (node, (light + heavy, 2 * light, 2 * light))
        heapq.heappush(heap, (light + heavy, node))
        node += 1
    out: dict[str | None, list[tuple[int, int, int]]] = {}
    for i, s in enumerate(names):
        out[s] = []
        while i in up:
            i, step = up[i]
            out[s].append(step)
    return out


def slot_of(block: int, path: list[tuple[int, int, int]]) -> int:
    """The slot, from 0, of a source's block, from 0."""
    at = block + 1
    for pair, addend, twice in path:
        at = ((2 * at - 1) * pair + addend) // twice
    return at - 1


def _exact(docs: DataFrame, counts: dict[str | None, int], weights: dict[str | None, float], block_rows: int) -> DataFrame:
    """mix_sources by the exact weights."""
    whole = whole_weights({s: weights.get(s, 0) for s in counts})
    way, total = paths(whole), sum(whole.values())
    blocks = {s: -(-n // block_rows) for s, n in counts.items()}
    end = max(((slot_of(blocks[s] - 1, way[s]) + 1) for s in way), default=0)
    start = dict.fromkeys(counts, 0)
    for s in sorted((s for s in counts if s not in way), key=lambda s: (s is not None, s)):
        start[s], end = end, end + blocks[s]
    if end > MOST // 4:
        raise ValueError("a weight is too small for its source's blocks: slots pass the range of whole numbers")
    kind = pa.decimal128(20)
    step = pa.struct([("t", pa.decimal128(19)), ("c", kind), ("d", kind)])
    rows = [{"_s": s, "_start": start[s], "_target": whole[s] / total, "_path": [dict(zip("tcd", x, strict=True)) for x in way.get(s, [])]} for s in counts]
    shares = docs.sparkSession.createDataFrame(
        pa.Table.from_pylist(rows, pa.schema([("_s", pa.string()), ("_start", pa.int64()), ("_target", pa.float64()), ("_path", pa.list_(step))]))
    )
    numbered = ranked(docs, ["source"], "doc_id", "_rank").withColumns({"block": F.floor(F.col("_rank") / block_rows), "place": (F.col("_rank") % block_rows).cast("int")})
    placed = numbered.join(F.broadcast(shares) if len(rows) <= 10_000 else shares, F.col("source").eqNullSafe(F.col("_s")))
    slot = F.expr("aggregate(_path, CAST(block + 1 AS BIGINT), (i, x) -> CAST((CAST(2 * i - 1 AS DECIMAL(18, 0)) * x.t + x.c) DIV x.d AS BIGINT)) - 1 + _start")
    return placed.withColumns({"slot": slot, "target": F.col("_target")}).select(*docs.columns, "block", "slot", "place", "target")


def _literal(value: str | None) -> str:
    return "CAST(NULL AS STRING)" if value is None else "'" + value.replace("\\", "\\\\").replace("'", "\\'") + "'"


def mix_sources(docs: DataFrame, weights: dict[str | None, float] | None = None, *, power: float = 0.5, block_rows: int = BLOCK_ROWS, period: int | None = PERIOD) -> DataFrame:
    """Give each row of docs (doc_id, source) its block, slot and place within the block, and its source's target.

    weights: by source, kept exactly; None: row counts to the given power, so that small sources come up more often, in
    whole parts of period, or exactly where it is None or there are more sources. Rows in order of (slot, place) are the mixture.
    """
    spark = docs.sparkSession
    docs = docs.drop("block", "slot", "place", "target")
    counts = {r.source: r.n for r in docs.groupBy("source").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return docs.withColumns({"block": F.lit(0).cast("bigint"), "slot": F.lit(0).cast("bigint"), "place": F.lit(0), "target": F.lit(0.0)})
    if weights is not None or period is None or len(counts) > period:
        return _exact(docs, counts, weights if weights is not None else {s: n**power for s, n in counts.items()}, block_rows)
    parts = quotas({s: n**power for s, n in counts.items()}, period)
    order = fair_schedule([q for _, q in parts])
    values = ", ".join(f"({_literal(parts[i][0])}, {nth}, {slot}, {parts[i][1]})" for slot, (i, nth) in enumerate(order))
    plan = spark.sql(f"SELECT * FROM VALUES {values} AS t(_source, _nth_block, _slot, _quota)")
    numbered = ranked(docs, ["source"], "doc_id", "_rank").withColumns({"block": F.floor(F.col("_rank") / block_rows), "place": (F.col("_rank") % block_rows).cast("int")})
    shares = spark.sql("SELECT * FROM VALUES " + ", ".join(f"({_literal(s)}, {q})" for s, q in parts) + " AS t(_s, _q)")
    numbered = numbered.join(F.broadcast(shares), F.col("source").eqNullSafe(F.col("_s")))
    at = F.col("source").eqNullSafe(F.col("_source")) & (F.col("block") % F.col("_q") == F.col("_nth_block"))
    placed = numbered.join(F.broadcast(plan), at)
    return placed.withColumns({"slot": F.floor(F.col("block") / F.col("_q")) * period + F.col("_slot"), "target": F.col("_q") / F.lit(float(period))}).select(
        *docs.columns, "block", "slot", "place", "target"
    )


def oracle(block_rows: int = BLOCK_ROWS, period: int = PERIOD) -> str:
    """DuckDB SQL of mix_sources with weights by the square root of row counts."""
    return f"""
    WITH RECURSIVE n AS (SELECT source, count(*) AS n FROM documents GROUP BY source),
    w AS (SELECT source, sqrt(n) / (SELECT sum(sqrt(n)) FROM n) * ({period} - (SELECT count(*) FROM n)) AS e FROM n),
    f AS (SELECT source, floor(e)::BIGINT AS whole, row_number() OVER (ORDER BY round(floor(e) - e, 9), source) AS r FROM w),
    q AS (SELECT source, whole + 1 + (CASE WHEN r <= {period} - (SELECT count(*) FROM n) - (SELECT sum(whole) FROM f) THEN 1 ELSE 0 END) AS q FROM f),
    o AS (SELECT list(source ORDER BY q DESC, source) AS s, list(q ORDER BY q DESC, source) AS q FROM q),
    step AS (
        SELECT -1::BIGINT AS slot, [0::BIGINT for x in q] AS done, 0::BIGINT AS who FROM o
        UNION ALL
        SELECT slot + 1, [done[i] + (CASE WHEN i = pick THEN 1 ELSE 0 END) for i in range(1, len(done) + 1)], pick
        FROM (
            SELECT slot, done, list_position(due, list_min(due))::BIGINT AS pick
            FROM (
                SELECT slot, done, [(CASE WHEN done[i] * {period} // q[i] <= slot + 1 THEN ((done[i] + 1) * {period} + q[i] - 1) // q[i] ELSE 1000000000 END) for i in range(1, len(done) + 1)] AS due
                FROM step, o WHERE slot < {period} - 1
            )
        )
    ),
    plan AS (SELECT s[who] AS source, q[who] AS quota, done[who] - 1 AS nth, slot FROM step, o WHERE who > 0),
    d AS (SELECT doc_id, source, row_number() OVER (PARTITION BY source ORDER BY doc_id) - 1 AS rk FROM documents)
    SELECT d.doc_id, d.source, (d.rk // {block_rows})::BIGINT AS block, (d.rk // {block_rows} // p.quota * {period} + p.slot)::BIGINT AS slot,
           (d.rk % {block_rows})::INTEGER AS place, p.quota / {float(period)} AS target
    FROM d JOIN plan p ON d.source = p.source AND d.rk // {block_rows} % p.quota = p.nth
    """
