"""Sharding by a consistent-hash ring with virtual nodes and bounded loads, with DataFrame operations only.

Every shard has virtual nodes on a ring; a row belongs to the arc that its id hashes into, and the arc to the
next virtual node clockwise. A shard takes rows up to its bound; what overflows goes on clockwise to the
next shard with room. Bounds of n // shards or one more make row counts differ by one at most, whatever
the hash does. Only counts by arc, of which there are shards times virtual nodes, reach the driver.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import literal_rows, seeded_hash, settle

SHARDS = 16
VIRTUAL = 64  # virtual nodes a shard
RING = 1 << 32  # places on the ring
CELL_ROWS = 50_000  # rows of an arc that one task ranks


def ring(shards: int = SHARDS, virtual: int = VIRTUAL) -> list[tuple[int, int]]:
    """(place, shard) of all virtual nodes, clockwise; an arc ends at its node."""
    nodes = sorted((zlib.crc32(f"shard {s} node {v}".encode()) * 2654435761 % RING, s) for s in range(shards) for v in range(virtual))
    return list({p: (p, s) for p, s in reversed(nodes)}.values())[::-1]


def place(doc_id: str) -> Column:
    """A row's place on the ring, from its id alone."""
    return F.shiftright(seeded_hash("ring", F.col(doc_id)), 28)


def bounds(total: int, shards: int) -> list[int]:
    """Row bounds at most one apart that add up to the total."""
    return [total // shards + (s < total % shards) for s in range(shards)]


def overflow(counts: list[int], owners: list[int], bound: list[int]) -> list[tuple[int, int, int, int, int]]:
    """(arc, from, to, shard, slot): which ranks of each arc go to which shard, and the slot that the first of them takes.

    In rounds: every arc offers what it has left to its own shard, then to the one of the next arc clockwise,
    and so on, arcs in clockwise order within a round.
    """
    left, room = list(counts), list(bound)
    begun, out, n = [0] * len(counts), [], len(owners)
    hop = 0
    while any(left):
        if hop >= n:
            raise ValueError("the bounds hold fewer rows than there are")
        for a in range(n):
            if left[a]:
                s = owners[(a + hop) % n]
                take = min(left[a], room[s])
                if take:
                    out.append((a, begun[a], begun[a] + take, s, bound[s] - room[s]))
                    begun[a] += take
                    left[a] -= take
                    room[s] -= take
        hop += 1
    return out


def arc_of(at: Column, nodes: list[tuple[int, int]]) -> Column:
    """Index of the first node at or clockwise of a place."""
    places = [p for p, _ in nodes]
    # nodes of each 256th of the ring in one short array: no scan over the whole ring
    slices = []
    for k in range(256):
        lo, hi = bisect_left(places, k * (RING // 256)), bisect_left(places, (k + 1) * (RING // 256))
        slices.append((lo, places[lo:hi]))
    table = F.array(*[F.struct(F.lit(lo).alias("lo"), F.array(*[F.lit(p).cast("long") for p in ps]).cast("array<long>").alias("ps")) for lo, ps in slices])
    own = table[F.shiftright(at, 24).cast("int")]
    past = F.size(F.filter(own["ps"], lambda p: p < at))
    return ((own["lo"] + past) % len(nodes)).cast("int")


def assign_rows(rows: DataFrame, doc_id: str = "doc_id", shards: int = SHARDS, virtual: int = VIRTUAL, tie: list[str] | None = None) -> DataFrame:
    """rows with shard and slot: shard row counts at most one apart, slots gapless from 0 in each.

    Ranks inside an arc follow the id and the `tie` columns, so rows that are alike in these may swap slots; an id that
    holds very many rows is ranked in parts. Null ids have a place of their own. An empty table gives an empty result. Columns named shard, slot or
    beginning with _ring must not be in rows.
    """
    nodes = ring(shards, virtual)
    ids = [doc_id, *(tie or [])]
    placed = rows.withColumn("_ring_at", place(doc_id)).withColumn("_ring_arc", arc_of(F.col("_ring_at"), nodes))
    # rows of one arc are ranked in cells, by content; rows that are alike in all of `ids` may be told apart by their place in the table
    placed = placed.withColumn("_ring_hash", F.xxhash64("_ring_at", *ids)).withColumn("_ring_row", F.xxhash64(F.monotonically_increasing_id()))
    placed = settle(placed, "placed")
    total = placed.count()
    arc = ["_ring_arc", "_ring_cell"]
    placed = placed.withColumn("_ring_cell", F.pmod("_ring_hash", F.lit(max(1, total // (len(nodes) * CELL_ROWS)))))
    full = placed.groupBy(*arc).agg(F.count("*").alias("n")).where(F.col("n") > 4 * CELL_ROWS).select(*arc, F.ceil(F.col("n") / CELL_ROWS).alias("_ring_parts"))
    placed = placed.join(full, arc, "left").withColumn("_ring_part", F.coalesce(F.pmod("_ring_row", F.col("_ring_parts")), F.lit(0)))
    arc += ["_ring_part"]
    cells = settle(placed.groupBy(*arc).agg(F.count("*").alias("n")), "cells")
    counts = {r["_ring_arc"]: r["n"] for r in cells.groupBy("_ring_arc").agg(F.sum("n").alias("n")).collect()}  # one row an arc
    moves = overflow([counts.get(a, 0) for a in range(len(nodes))], [s for _, s in nodes], bounds(total, shards))
    # the moves of each arc as an array: a few thousand numbers in all, bounded by the ring
    spark = rows.sparkSession
    table = literal_rows(spark, moves, "_ring_arc int, lo long, hi long, shard int, slot long")
    table = table.groupBy("_ring_arc").agg(F.collect_list(F.struct("lo", "hi", "shard", "slot")).alias("_ring_moves"))
    upto = W.partitionBy("_ring_arc").orderBy("_ring_cell", "_ring_part").rowsBetween(W.unboundedPreceding, -1)
    before = cells.select(*arc, F.coalesce(F.sum("n").over(upto), F.lit(0)).alias("_ring_before"))
    nth = F.row_number().over(W.partitionBy(*arc).orderBy("_ring_at", *ids))
    ranked = placed.join(before, arc).withColumn("_ring_rank", F.col("_ring_before") + nth - 1).join(F.broadcast(table), "_ring_arc")
    mine = F.filter("_ring_moves", lambda m: (m["lo"] <= F.col("_ring_rank")) & (F.col("_ring_rank") < m["hi"]))[0]
    out = ranked.withColumn("_ring_move", mine).withColumn("shard", F.col("_ring_move.shard"))
    out = out.withColumn("slot", F.col("_ring_move.slot") + F.col("_ring_rank") - F.col("_ring_move.lo"))
    return out.select(*rows.columns, "shard", "slot")


def write_shards(docs: DataFrame, path: str, doc_id: str = "doc_id", shards: int = SHARDS) -> None:
    """Writes docs as one folder a shard, `shard=0` and so on, each file in the order of slots: (slot, row struct of all columns)."""
    rows = docs.select(F.col(doc_id).cast("long").alias("id"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    assign_rows(rows, "id", shards).select("shard", "slot", "row").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def measured(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, size, text_crc32): UTF-8 bytes plus 1, and the unsigned crc32; null texts count as empty."""
    raw = F.coalesce(F.col(text), F.lit("")).cast("binary")
    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), (F.length(raw) + 1).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"))
