"""Consistent-hash ring with virtual nodes and bounded loads.

Each shard owns ``vnodes`` points of a 64-bit ring. A document belongs to the
arc that ends at the next point clockwise of its hash. A shard takes documents
up to its capacity; what overflows an arc continues clockwise to the next shard
with room. Instead of placing documents one at a time, the documents of each arc
are counted in a distributed aggregate, the (bounded) table of arcs is settled
once, and every document finds its place from its rank inside its arc.

With slack 0 the capacities are the row counts of a perfectly even split, so
shards differ by at most one row; with a positive slack fewer documents leave
their own arc and no shard exceeds ``ceil((1 + slack) * rows / shards)``.

An arc of more than ``HOT_ARC`` documents, which only a key makes that very many rows
share, is ranked in parts: its rows are dealt by their number, each part is ranked by
itself and begins where the part before ends.

Nulls: a document without an id takes size and checksum for its key; a null text has no
bytes. Repeated rows are separate rows; ties in the ring order are broken by id, size and
checksum, and rows equal in all of them are alike. A very long text counts by its bytes.
An empty table gives an empty result. Columns of the input that are named like an
output are replaced by it.
"""

from __future__ import annotations

import json
import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise

VNODES = 128
CELL_BITS = 14
#: Documents of one arc that are ranked in one go.
HOT_ARC = 1 << 20


@dataclass(frozen=True)
class Segment:
    """Ranks ``first`` to ``first + rows - 1`` of an arc, and where they start in their shard."""

    arc: int
    first: int
    rows: int
    shard: int
    slot: int


def ring_points(spark: SparkSession, n_shards: int, vnodes: int = VNODES) -> DataFrame:
    """(arc, shard, point) in ring order; a shard's points do not depend on the number of shards."""
    point = F.xxhash64(F.lit("ring"), F.col("shard"), F.col("replica"))
    points = (
        spark.range(0, n_shards * vnodes, 1, 1)
        .select((F.col("id") % n_shards).cast("int").alias("shard"), F.floor(F.col("id") / n_shards).alias("replica"))
        .select("shard", point.alias("point"))
    )
    return points.select((F.row_number().over(Window.orderBy("point", "shard")) - 1).alias("arc"), "shard", "point")


def settle(counts: dict[int, int], owners: list[int], capacity: list[int]) -> list[Segment]:
    """Flow of the arcs' documents round the ring, on counts alone.

    Shards first take from their own arcs in ring order; what is left moves on
    arc by arc, and each arc's shard takes from it, the nearest arcs first.
    """
    room, filled, out = list(capacity), [0] * len(capacity), []

    def take(arc: int, first: int, rows: int, shard: int) -> int:
        got = min(rows, room[shard])
        if got:
            out.append(Segment(arc, first, got, shard, filled[shard]))
            room[shard] -= got
            filled[shard] += got
        return got

    moving = []
    for arc, shard in enumerate(owners):
        rows = counts.get(arc, 0)
        got = take(arc, 0, rows, shard)
        if rows > got:
            moving.append((arc, got, rows - got))
    step = 1
    while moving:
        if step > len(owners):
            raise ValueError("the shards have less room than there are rows")
        left = []
        for arc, first, rows in moving:
            got = take(arc, first, rows, owners[(arc + step) % len(owners)])
            if rows > got:
                left.append((arc, first + got, rows - got))
        moving, step = left, step + 1
    return out


def capacities(rows: int, n_shards: int, slack: float) -> list[int]:
    if slack <= 0:
        return [rows // n_shards + (k < rows % n_shards) for k in range(n_shards)]
    return [math.ceil((1 + slack) * rows / n_shards - 1e-9)] * n_shards


def with_arc(df: DataFrame, ring: DataFrame, position: Column, n_points: int) -> DataFrame:
    """Adds ``__arc``: the ring is cut into equal cells, and a cell lists the few points inside it and the arc at its start.

    The cell table has 2^CELL_BITS rows whatever the data, so it is broadcast.
    """
    spark = df.sparkSession
    cell = lambda h: F.shiftrightunsigned(h.bitwiseXOR(F.lit(-(2**63))), 64 - CELL_BITS)
    inside = ring.groupBy(cell(F.col("point")).alias("__cell")).agg(F.sort_array(F.collect_list("point")).alias("__points"))
    cells = (
        spark.range(0, 2**CELL_BITS, 1, 1)
        .withColumnRenamed("id", "__cell")
        .join(F.broadcast(inside), "__cell", "left")
        .withColumn("__points", F.coalesce("__points", F.array().cast("array<bigint>")))
        .withColumn("__before", F.coalesce(F.sum(F.size("__points")).over(Window.orderBy("__cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    )
    placed = df.withColumn("__at", position).withColumn("__cell", cell(F.col("__at"))).join(F.broadcast(cells), "__cell")
    return placed.withColumn("__arc", ((F.col("__before") + F.size(F.filter("__points", lambda p: p < F.col("__at")))) % n_points).cast("int")).drop("__cell", "__points", "__before")


def ring_shards(
    docs: DataFrame,
    n_shards: int,
    key: Column,
    order: list[str],
    vnodes: int = VNODES,
    slack: float = 0.0,
) -> DataFrame:
    """Adds ``shard`` (int), ``slot`` (long, gapless from 0 in each shard) and ``home`` (the shard of the document's own arc).

    ``key`` is what is hashed to the ring, ``order`` the columns that break ties of the ring order.
    """
    spark = docs.sparkSession
    ring = ring_points(spark, n_shards, vnodes)
    n_points = n_shards * vnodes
    position = F.xxhash64(F.lit("key"), key)
    counts = {r[0]: r[1] for r in with_arc(docs.select(key.alias("__key")), ring, F.xxhash64(F.lit("key"), F.col("__key")), n_points).groupBy("__arc").count().collect()}
    owners = [r[0] for r in ring.orderBy("arc").select("shard").collect()]
    segments = settle(counts, owners, capacities(sum(counts.values()), n_shards, slack))
    by_arc: dict[int, list[dict]] = {}
    for s in segments:
        by_arc.setdefault(s.arc, []).append({"first": s.first, "rows": s.rows, "shard": s.shard, "slot": s.slot})
    table = [{"arc": arc, "home": owners[arc], "parts": parts} for arc, parts in by_arc.items()]
    plan = spark.range(0, 1, 1, 1).select(
        F.inline(F.from_json(F.lit(json.dumps(table)), "array<struct<arc:int,home:int,parts:array<struct<first:bigint,rows:bigint,shard:int,slot:bigint>>>>"))
    )
    hot = {arc: -(-rows // HOT_ARC) for arc, rows in counts.items() if rows > HOT_ARC}
    on_arcs = with_arc(docs, ring, position, n_points)
    if hot:
        numbered = materialise(on_arcs.withColumn("__row", F.monotonically_increasing_id()), "ring-rows")  # written, so a row keeps its number
        look = lambda table, key, kind: F.try_element_at(F.from_json(F.lit(json.dumps(table)), f"map<string,{kind}>"), key)
        parts = look(hot, F.col("__arc").cast("string"), "int")
        on_arcs = numbered.withColumn("__part", F.coalesce(F.pmod(F.xxhash64("__row"), parts), F.lit(0)).cast("int")).drop("__row")
        of_parts = on_arcs.where(F.col("__arc").isin(list(hot))).groupBy("__arc", "__part").count().collect()
        starts, before = {}, dict.fromkeys(hot, 0)
        for arc, part, rows in sorted(map(tuple, of_parts)):
            starts[f"{arc}:{part}"] = before[arc]
            before[arc] += rows
        offset = look(starts, F.concat_ws(":", "__arc", "__part"), "bigint")
    else:
        on_arcs, offset = on_arcs.withColumn("__part", F.lit(0)), F.lit(None)
    rank = F.row_number().over(Window.partitionBy("__arc", "__part").orderBy("__at", *order)).cast("long") - 1
    ranked = on_arcs.withColumn("__rank", rank + F.coalesce(offset, F.lit(0))).drop("__part")
    placed = ranked.join(F.broadcast(plan.toDF("__arc", "__home", "__parts")), "__arc")
    part = F.element_at(F.filter("__parts", lambda p: (F.col("__rank") >= p["first"]) & (F.col("__rank") < p["first"] + p["rows"])), 1)
    return placed.withColumn("__part", part).select(
        *[F.col(c) for c in docs.columns if c not in ("shard", "slot", "home")],
        F.col("__part.shard").alias("shard"),
        (F.col("__part.slot") + F.col("__rank") - F.col("__part.first")).alias("slot"),
        F.col("__home").alias("home"),
    )


def op9_ring_sharding(spark: SparkSession, sf_dir: str, n_shards: int = 40) -> DataFrame:
    """All documents in shards whose row counts differ by at most one."""
    text = F.coalesce(F.col("text"), F.lit(""))
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(
        "doc_id", (F.octet_length(text).cast("long") + 16).alias("size"), F.crc32(text).alias("text_crc32")
    )
    key = F.coalesce(F.when(F.col("doc_id").isNotNull(), F.xxhash64("doc_id")), F.xxhash64(F.lit("lost"), "size", "text_crc32"))
    placed = ring_shards(docs, n_shards, key, ["doc_id", "size", "text_crc32"])
    return placed.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), F.col("home").alias("home_shard")
    )
