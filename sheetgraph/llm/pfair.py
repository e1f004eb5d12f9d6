"""Mixing sources to target weights by Pfair scheduling.

Rows of a source are dealt into blocks. With weight q/H (q quanta of H in all), block i of a source is
released at slot floor(i*H/q) and due by slot ceil((i+1)*H/q); the released block that is due first takes
each slot. Releases keep a source from running ahead, deadlines from falling behind: at any slot its
blocks so far differ from its share by less than one. The schedule repeats after H slots, so one period
gives every block's slot in closed form: the driver plans with a row for each source, never with blocks.
When a source has no block left, a new epoch starts with the weights of those that remain.

Rows are numbered inside their source in two levels, by hash bucket and inside it, so a source that holds
a third of all rows is no task's burden. No row is dropped or repeated.

Defined results: a null source and sources without quanta of their own share the pool named REST with
rest_quanta; equal rows get places of their own; null keys sort first; an empty table stays empty; columns
named like the results are replaced.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sheetgraph.llm._shared import unused, without

REST = "(rest)"
#: Rows a bucket numbers in one task on average, and partitions of the ordered result at most.
BUCKET_ROWS, MOST_PARTS = 2_000_000, 50_000


def period(quanta: dict[str, int]) -> dict[str, list[int]]:
    """Slots of each source in one period of sum(quanta) slots: earliest deadline first among the released."""
    total = sum(quanta.values())
    slots: dict[str, list[int]] = {s: [] for s in quanta}
    released: list[tuple[int, str]] = []
    starts = sorted((i * total // q, -(-(i + 1) * total // q), s) for s, q in quanta.items() for i in range(q))
    at = 0
    for slot in range(total):
        while at < len(starts) and starts[at][0] <= slot:
            heapq.heappush(released, starts[at][1:])
            at += 1
        due, source = heapq.heappop(released)
        if due <= slot:
            raise AssertionError("a deadline was missed")
        slots[source].append(slot)
    return slots


def epochs(blocks: dict[str, int], quanta: dict[str, int]) -> list[dict]:
    """Segments: source, from_block, blocks, start slot, quanta, period length, offsets in the period."""
    left = {s: n for s, n in blocks.items() if n > 0}
    done = dict.fromkeys(left, 0)
    start, out = 0, []
    while left:
        now = {s: quanta[s] for s in left}
        slots, total = period(now), sum(now.values())

        def slot_of(s: str, i: int) -> int:
            return i // now[s] * total + slots[s][i % now[s]]

        end = min(slot_of(s, n - 1) for s, n in left.items()) + 1
        for s in sorted(left):
            whole, rest = divmod(end, total)
            n = whole * now[s] + sum(x < rest for x in slots[s])
            if n:
                out.append({"source": s, "from_block": done[s], "blocks": n, "start": start, "quanta": now[s], "total": total, "offsets": slots[s]})
            done[s] += n
            left[s] -= n
        left = {s: n for s, n in left.items() if n}
        start += end
    return out


def schedule(docs: DataFrame, quanta: dict[str, int], rest_quanta: int = 1, block_rows: int = 64, key: str = "doc_id", source: str = "source", buckets: int | None = None, prefix: str = "") -> DataFrame:
    """All columns of docs, then pool, block, slot and position (slot * block_rows + place in the block).

    buckets: parts in which a source's rows are numbered, by default one for BUCKET_ROWS rows and 64 at least.
    """
    if min([rest_quanta, *quanta.values()]) < 1 or block_rows < 1:
        raise ValueError("quanta and block_rows are whole numbers above 0")
    docs = without(docs, *(prefix + c for c in ("pool", "block", "slot", "position")))
    own = ("pool", "hash", "part", "rank", "block", "offset", "from", "to", "start", "quanta", "total", "slots")
    p = dict(zip(own, unused(docs.columns, *(f"__{c}" for c in own))))
    if buckets is None:
        buckets = max(64, -(-docs.count() // BUCKET_ROWS))
    pool = F.when(F.col(source).isin(*quanta), F.col(source)).otherwise(F.lit(REST)) if quanta else F.lit(REST)
    rows = docs.withColumn(p["pool"], pool).withColumn(p["hash"], F.xxhash64(key, F.lit("mix")))
    rows = rows.withColumn(p["part"], F.pmod(F.col(p["hash"]), F.lit(buckets)).cast("int"))
    sizes = rows.groupBy(p["pool"], p["part"]).agg(F.count(F.lit(1)).alias("n"))
    found = sizes.collect()  # pools * buckets rows at most: the pools are those the caller named, and one
    counts: dict[str, int] = {}
    offsets = []
    for r in sorted(found, key=lambda r: (r[0], r[1])):
        offsets.append((r[0], r[1], counts.get(r[0], 0)))
        counts[r[0]] = counts.get(r[0], 0) + r["n"]
    plan = epochs({s: -(-n // block_rows) for s, n in counts.items()}, quanta | {REST: rest_quanta})
    spark = docs.sparkSession
    offsets_df = spark.createDataFrame(offsets or [("", 0, 0)], f"`{p['pool']}` string, `{p['part']}` int, `{p['offset']}` long")
    plan_df = spark.createDataFrame([(e["source"], e["from_block"], e["from_block"] + e["blocks"], e["start"], e["quanta"], e["total"], e["offsets"]) for e in plan] or [("", 0, 0, 0, 1, 1, [0])], f"`{p['pool']}` string, `{p['from']}` long, `{p['to']}` long, `{p['start']}` long, `{p['quanta']}` long, `{p['total']}` long, `{p['slots']}` array<long>")
    inside = Window.partitionBy(p["pool"], p["part"]).orderBy(p["hash"], key)
    rows = rows.withColumn(p["rank"], F.row_number().over(inside) - 1).join(F.broadcast(offsets_df), [p["pool"], p["part"]])
    rows = rows.withColumn(p["rank"], F.col(p["offset"]) + F.col(p["rank"]))
    rows = rows.withColumn(p["block"], F.floor(F.col(p["rank"]) / block_rows).cast("long"))
    block = F.col(f"r.{p['block']}")
    rows = rows.alias("r").join(F.broadcast(plan_df).alias("e"), (F.col(f"r.{p['pool']}") == F.col(f"e.{p['pool']}")) & (block >= F.col(f"e.{p['from']}")) & (block < F.col(f"e.{p['to']}")))
    i = block - F.col(p["from"])
    slot = F.col(p["start"]) + F.floor(i / F.col(p["quanta"])) * F.col(p["total"]) + F.element_at(p["slots"], (F.pmod(i, F.col(p["quanta"])) + 1).cast("int"))
    return rows.select(
        *[F.col(f"r.`{c}`") for c in docs.columns],
        F.col(f"r.{p['pool']}").alias(prefix + "pool"),
        block.alias(prefix + "block"),
        slot.cast("long").alias(prefix + "slot"),
        (slot * block_rows + F.pmod(F.col(p["rank"]), F.lit(block_rows))).cast("long").alias(prefix + "position"),
    )


def in_order(scheduled: DataFrame, rows_per_part: int = 10_000, prefix: str = "") -> DataFrame:
    """Rows in the order of their positions, partition by partition; larger ones beyond MOST_PARTS partitions."""
    position = F.col(prefix + "position")
    last = scheduled.agg(F.max(position)).first()[0]
    per = max(rows_per_part, 0 if last is None else -(-(last + 1) // MOST_PARTS))
    parts = 1 if last is None else int(last // per) + 1
    return scheduled.repartitionById(parts, F.floor(position / per).cast("int")).sortWithinPartitions(position)
