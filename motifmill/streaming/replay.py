"""Updates as streams: micro-batches of edges keep graph, store and matches up to date.

Each micro-batch is one update. State is a set of Parquet folders named by batch, the
last of which a small pointer file names; a batch that is replayed after a failure
finds its own folder written over, so it changes nothing twice.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from pathlib import PurePosixPath

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.operators.compress import decompress
from motifmill.operators.incremental import drop_removed, patch_set
from motifmill.operators.store import Partitioner, build_store, normalize_update, star_lists, update_store, updated_edges
from motifmill.plans.pattern import Order, Pattern


class StateStore:
    """Versions of (edges, store, matches) below a folder; version -1 is the start."""

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder

    def path(self, version: int, name: str) -> str:
        return str(PurePosixPath(self.folder.replace("file://", "", 1)) / f"batch_id={version}" / name) if self.folder.startswith("file://") else f"{self.folder}/batch_id={version}/{name}"

    def write(self, version: int, **frames: DataFrame) -> None:
        for name, frame in frames.items():
            frame.write.mode("overwrite").parquet(self.path(version, name))

    def read(self, version: int, name: str) -> DataFrame:
        return self.spark.read.parquet(self.path(version, name))


class Maintainer:
    """Maintains one pattern over batches of (op, u, v) with ``foreachBatch``."""

    def __init__(self, spark: SparkSession, folder: str, p: Pattern, cover: frozenset[str], order: Order, h: Partitioner):
        self.state, self.p, self.cover, self.order, self.h = StateStore(spark, folder), p, cover, order, h
        self.last = -1

    def start(self, edges: DataFrame, matches: DataFrame) -> None:
        self.state.write(-1, edges=edges)
        edges = self.state.read(-1, "edges")
        self.state.write(-1, store=build_store(edges, self.h), matches=matches)

    def batch(self, update: DataFrame, batch_id: int) -> None:
        """Applies one batch to the version before it and writes its own; running it again gives the same."""
        before = batch_id - 1
        edges, store, matches = (self.state.read(before, n) for n in ("edges", "store", "matches"))
        self.state.write(batch_id, update=update.select("op", F.col("u").cast("bigint").alias("u"), F.col("v").cast("bigint").alias("v")))
        deleted, added = normalize_update(edges, self.state.read(batch_id, "update"))
        self.state.write(batch_id, deleted=deleted, added=added)
        deleted, added = self.state.read(batch_id, "deleted"), self.state.read(batch_id, "added")
        self.state.write(batch_id, edges=updated_edges(edges, deleted, added), store=update_store(store, star_lists(store, deleted, added), deleted, added, self.h))
        patch = patch_set(self.state.read(batch_id, "store"), self.p, self.cover, self.order, added, self.h)
        self.state.write(batch_id, patch=patch)
        survivors = drop_removed(matches, self.p, deleted, self.cover)
        self.state.write(batch_id, matches=survivors.unionByName(self.state.read(batch_id, "patch")))
        self.last = batch_id

    def run(self, updates: DataFrame, checkpoint: str, available_now: bool = True) -> None:
        """Consumes a stream of (op, u, v)."""
        writer = updates.writeStream.foreachBatch(self.batch).option("checkpointLocation", checkpoint)
        query = (writer.trigger(availableNow=True) if available_now else writer).start()
        query.awaitTermination()

    def current(self) -> DataFrame:
        return decompress(self.state.read(self.last, "matches"), self.p, self.cover, self.order)

    def changes(self, batch_id: int) -> DataFrame:
        """(sign, f_...) of one batch."""
        old, now = (decompress(self.state.read(b, "matches"), self.p, self.cover, self.order) for b in (batch_id - 1, batch_id))
        come = decompress(self.state.read(batch_id, "patch"), self.p, self.cover, self.order)
        return come.withColumn("sign", F.lit(1)).unionByName(old.exceptAll(now).withColumn("sign", F.lit(-1)))


def apply_stream(start: Maintainer, batches: Iterator[DataFrame]) -> Maintainer:
    """A sequence of batches without a streaming source; one-edge batches are the stream of single edges."""
    for k, update in enumerate(batches):
        start.batch(update, k)
    return start


def one_edge_batches(update: DataFrame) -> Iterator[DataFrame]:
    """All rows of an update as batches of one edge, fetched a partition at a time."""
    for row in update.select("op", "u", "v").toLocalIterator():
        yield update.sparkSession.createDataFrame([tuple(row)], "op string, u bigint, v bigint")


def read_updates(spark: SparkSession, folder: str, per_trigger: int = 1) -> DataFrame:
    """A file stream of Parquet updates, some files a micro-batch."""
    return spark.readStream.schema("batch_id bigint, op string, u bigint, v bigint").option("maxFilesPerTrigger", per_trigger).parquet(folder)


def event_edges(events: DataFrame, delay: str = "1 hour", every: str = "1 day") -> DataFrame:
    """(window, user_id, n) of a stream of events: late ones beyond the delay are dropped; a window's users make its co-activity."""
    marked = events.withWatermark("ts", delay)
    return marked.groupBy(F.window("ts", every), "user_id").agg(F.count("*").alias("n"))


def sliding_updates(pairs: DataFrame, days: int) -> Callable[[int], DataFrame]:
    """Batches of a sliding window over dated pairs (day, u, v): on each day, edges whose first support enters come
    and edges whose last support leaves go."""
    support = pairs.where("u <> v").select("day", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()

    def alive(day: int) -> DataFrame:
        return support.where((F.col("day") > day - days) & (F.col("day") <= day)).select("u", "v").distinct()

    def batch(day: int) -> DataFrame:
        now, before = alive(day), alive(day - 1)
        come = now.join(before, ["u", "v"], "left_anti").select(F.lit("+").alias("op"), "u", "v")
        return come.union(before.join(now, ["u", "v"], "left_anti").select(F.lit("-").alias("op"), "u", "v"))

    return batch


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(session, user_id, n): session windows of a user's events; works on tables and streams."""
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
