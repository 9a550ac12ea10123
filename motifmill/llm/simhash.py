"""SimHash fingerprints and a Gray-order hierarchical index over them.

Fingerprints: the words of a text (A-Z lowered) give shingles; a bit is set when
it is set in over half of the shingles' XXH64 values (seed 42).

Index: the distinct fingerprints are sorted by Gray rank, where neighbours differ in few
bits, and cut into ranges of near-equal numbers. Every range is the root of a tree:
runs of neighbours form nodes, nodes form upper nodes, and each keeps the bits that all
its members share. The roots themselves form the top of the same tree, which is small
(``LEAST_RANGES`` roots, then one for ``RANGE_ROWS`` fingerprints, at most ``MAX_RANGES``) and
known to all tasks.

Search: every fingerprint is a query. It walks down from the top and drops a whole group
as soon as its differences from the group's shared bits exceed three; the roots that are
left are the ranges it travels to, where it walks on. For every two ranges one sends to
the other, whichever of the two by the parity of their numbers, which is enough for links
and halves the travel. With 2^p ranges a query travels to about half of the p-bit
patterns within three bits of its own, a number that grows with the cube of p and not
with the data. Nothing is compared outside the tree.

A range yields a spanning forest of the links it has found, not all pairs; the components
over all ranges follow by star contraction.

Nulls: a null text has no words and fingerprint zero; a null id takes the
component of its fingerprint (null if no other document is there). Repeated rows
are linked like copies. A very long text is one row of one task. An empty table gives
an empty result. Input columns named like an output are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise
from motifmill.llm.components import least_labels, star_components
from motifmill.llm.words import byte_slices, raw_texts

SEED = 42
DISTANCE = 3
#: Fingerprints of a range that a task holds with ease, and the least and most ranges. Queries travel less the fewer ranges
#: there are, so their number is the least one until ranges are full.
RANGE_ROWS, LEAST_RANGES, MAX_RANGES = 1 << 20, 64, 16384
#: Children of a node, and queries that walk down together.
FAN, TOGETHER = 4, 2048


def shingle_hashes(text: bytes, width: int) -> np.ndarray:
    """XXH64 values of the ``width``-word shingles of a UTF-8 text; a shorter text is one shingle, and one without words has none."""
    words = text.lower().split()
    if not words:
        return np.zeros(0, dtype="<u8")
    line = b" ".join(words)
    digest = xxhash.xxh64_intdigest
    if len(words) <= width:
        return np.array([digest(line, SEED)], dtype="<u8")
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = [0, *(ends[: len(words) - width]).tolist()]
    stops = (ends[width - 1 :] - 1).tolist()
    return np.array([digest(line[a:b], SEED) for a, b in zip(starts, stops, strict=True)], dtype="<u8")


def fingerprint(text: bytes, width: int) -> int:
    """64-bit SimHash of the ``width``-word shingles of a UTF-8 text."""
    return majority(shingle_hashes(text, width))


def majority(h: np.ndarray) -> int:
    """The bits that over half of 64-bit values have set."""
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(h), 4096):
        part = h[at : at + 4096]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(h), bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame, width: int = 3, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, fp long): the fingerprint's 64 bits as a signed number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in byte_slices(batches, 1, 4 << 20):
            values = np.array([fingerprint(t, width) for t in raw_texts(batch.column(1))], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values, pa.int64())], ["key", "fp"])

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(run, f"key {kind}, fp bigint")


def gray_rank(x: np.ndarray) -> np.ndarray:
    """Place of each code word in Gray order."""
    for shift in (1, 2, 4, 8, 16, 32):
        x = x ^ (x >> np.uint64(shift))
    return x


class GrayIndex:
    """Tree over groups in Gray order; a group is one fingerprint or, at the top of the index, a range.

    ``ones`` and ``zeros`` are the bits that all members of a group have set or unset.
    """

    def __init__(self, ones: np.ndarray, zeros: np.ndarray, sizes: np.ndarray | None = None):
        self.levels = [(ones, zeros)]
        self.sizes = [np.ones(len(ones), dtype=np.int64) if sizes is None else sizes]
        while len(self.levels[-1][0]) > FAN:
            starts = np.arange(0, len(self.levels[-1][0]), FAN)
            self.levels.append(tuple(np.bitwise_and.reduceat(x, starts) for x in self.levels[-1]))
            self.sizes.append(np.add.reduceat(self.sizes[-1], starts))
        #: Fingerprints ruled out by an upper node, and those compared one by one.
        self.pruned = self.compared = 0

    @classmethod
    def of(cls, codes: np.ndarray) -> GrayIndex:
        """Over fingerprints that are in Gray order."""
        return cls(codes, ~codes)

    def near(self, codes: np.ndarray, distance: int = DISTANCE) -> tuple[np.ndarray, np.ndarray]:
        """(place of the code, place of the group) for all groups whose shared bits differ from the code's in at most ``distance``."""
        found = [self._near(codes[k : k + TOGETHER], k, distance) for k in range(0, len(codes), TOGETHER)]
        return tuple(np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 2

    def _near(self, codes: np.ndarray, base: int, distance: int) -> tuple[np.ndarray, np.ndarray]:
        top = len(self.levels[-1][0])
        who, node = np.repeat(np.arange(len(codes)), top), np.tile(np.arange(top), len(codes))
        for depth in range(len(self.levels) - 1, -1, -1):
            ones, zeros = self.levels[depth]
            own = codes[who]
            close = np.bitwise_count((ones[node] & ~own) | (zeros[node] & own)) <= distance
            if depth:
                self.pruned += int(self.sizes[depth][node[~close]].sum())
            else:
                self.compared += len(node)
            who, node = who[close], node[close]
            if depth:
                who = np.repeat(who, FAN)
                node = (node[:, None] * FAN + np.arange(FAN)).ravel()
                real = node < len(self.levels[depth - 1][0])
                who, node = who[real], node[real]
        return who + base, node


def _range_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (part, visitor, fp, root) in the order of (part, visitor, fp); yields links between roots.

    The members of a range come first and become its tree; then queries from other ranges come by.
    """

    def spanning(u: np.ndarray, v: np.ndarray, roots: np.ndarray) -> pa.RecordBatch:
        label = least_labels(u, v, len(roots))
        linked = np.flatnonzero(label != np.arange(len(roots)))
        return pa.RecordBatch.from_arrays([pa.array(roots[linked]), pa.array(roots[label[linked]])], ["u", "v"])

    now, members, roots, index = None, [], [], None

    def plant() -> tuple[GrayIndex, np.ndarray, pa.RecordBatch]:
        codes, own = np.concatenate(members), np.concatenate(roots)
        order = np.argsort(gray_rank(codes), kind="stable")
        codes, own = codes[order], own[order]
        tree = GrayIndex.of(codes)
        who, met = tree.near(codes)
        return tree, own, spanning(who, met, own)

    for batch in batches:
        part, visitor, fp, root = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(4))
        fp = fp.view(np.uint64)
        bounds = np.flatnonzero(np.append(True, (part[1:] != part[:-1]) | (visitor[1:] != visitor[:-1]))) if len(part) else []
        for a, b in zip(bounds, [*bounds[1:], len(part)], strict=True):
            if part[a] != now:
                if members and index is None:
                    yield plant()[2]
                now, members, roots, index = part[a], [], [], None
            if not visitor[a]:
                members.append(fp[a:b])
                roots.append(root[a:b])
                continue
            if index is None:
                if not members:
                    continue  # a range without members has no visitors
                index, own, links = plant()
                yield links
            who, met = index.near(fp[a:b])
            seen, at = np.unique(who, return_inverse=True)
            if len(seen):
                met_own, place = np.unique(met, return_inverse=True)
                yield spanning(place, at + len(met_own), np.append(own[met_own], root[a:b][seen]))
    if members and index is None:
        yield plant()[2]


def gray_rank_column(fp: Column) -> Column:
    """Gray rank as a signed number whose order is that of the unsigned rank."""
    for shift in (1, 2, 4, 8, 16, 32):
        fp = fp.bitwiseXOR(F.shiftrightunsigned(fp, shift))
    return fp.bitwiseXOR(F.lit(-(1 << 63)))


def range_bounds(codes: DataFrame, ranges: int) -> np.ndarray:
    """Upper bounds of all ranges but the last, as signed ranks: approximate quantiles, which only set how even ranges are."""
    if ranges < 2:
        return np.zeros(0, dtype=np.int64)
    ranks = codes.select(gray_rank_column(F.col("fp")).cast("double").alias("rank"))
    cuts = ranks.approxQuantile("rank", [k / ranges for k in range(1, ranges)], 0.25 / ranges)
    return np.unique(np.clip(np.array(cuts), -(2.0**63), 2.0**63 - 1025).astype(np.int64))


def similar_links(codes: DataFrame, range_rows: int = RANGE_ROWS) -> DataFrame:
    """Links (u, v) between ids ``root`` of distinct fingerprints ``codes(fp, root)`` that span all pairs within three bits."""
    spark = codes.sparkSession
    rows = codes.count()
    bounds = range_bounds(codes, min(MAX_RANGES, max(LEAST_RANGES, -(-rows // range_rows))))

    def parts_of(fp: np.ndarray) -> np.ndarray:
        rank = (gray_rank(fp.view(np.uint64)) ^ np.uint64(1 << 63)).view(np.int64)
        return np.searchsorted(bounds, rank, side="left")

    def shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = batch.column(0).to_numpy(zero_copy_only=False)
            part = parts_of(fp)
            order = np.argsort(part, kind="stable")
            part, fp = part[order], fp[order]
            at = np.flatnonzero(np.append(True, part[1:] != part[:-1])) if len(part) else np.zeros(0, np.int64)
            if len(at):
                size = np.diff(np.append(at, len(part)))
                yield pa.RecordBatch.from_arrays([pa.array(part[at]), pa.array(np.bitwise_and.reduceat(fp, at)), pa.array(np.bitwise_and.reduceat(~fp, at)), pa.array(size)], ["part", "ones", "zeros", "size"])

    masks = codes.select("fp").mapInArrow(shared, "part bigint, ones bigint, zeros bigint, size bigint")
    masks = masks.groupBy("part").agg(F.bit_and("ones").alias("ones"), F.bit_and("zeros").alias("zeros"), F.sum("size").alias("size")).orderBy("part").collect()
    numbers = np.array([m["part"] for m in masks], dtype=np.int64)
    of = lambda name: np.array([m[name] for m in masks], dtype=np.int64)
    top = spark.sparkContext.broadcast((numbers, of("ones").view(np.uint64), of("zeros").view(np.uint64), of("size")))  # at most MAX_RANGES entries

    def travel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        numbers, ones, zeros, size = top.value
        tree = GrayIndex(ones, zeros, size)
        for batch in batches:
            for cut in range(0, batch.num_rows, TOGETHER):
                fp, root = (batch.column(k).slice(cut, TOGETHER).to_numpy(zero_copy_only=False) for k in range(2))
                home = parts_of(fp)
                who, to = tree.near(fp.view(np.uint64))
                to = numbers[to]
                here = home[who]
                go = (to != here) & (((to + here) % 2 == 0) == (to > here))
                who, to = who[go], to[go]
                part, visitor = np.append(home, to), np.repeat([False, True], [len(home), len(to)])
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(visitor), pa.array(np.append(fp, fp[who])), pa.array(np.append(root, root[who]))], ["part", "visitor", "fp", "root"])

    rows_of = codes.select("fp", "root").mapInArrow(travel, "part bigint, visitor boolean, fp bigint, root bigint")
    return rows_of.repartition("part").sortWithinPartitions("part", "visitor", "fp").mapInArrow(_range_links, "u bigint, v bigint")


def simhash_components(docs: DataFrame, width: int = 3, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, fp, component): the component is the least id reachable over links of at most three bits."""
    own = materialise(fingerprints(docs, width, text, key), "fingerprints")
    codes = materialise(own.where("key is not null").groupBy("fp").agg(F.min("key").alias("root")), "codes")
    labels = star_components(similar_links(codes))
    classes = codes.join(labels, F.col("root") == F.col("node"), "left").select(F.col("fp").alias("__fp"), F.coalesce("component", "root").alias("component"))
    return own.join(classes, F.col("fp") == F.col("__fp"), "left").select("key", "fp", "component")


def hex_code(fp: Column) -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and component of every document."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return simhash_components(docs).select(F.col("key").alias("doc_id"), hex_code(F.col("fp")).alias("fingerprint"), F.col("component").alias("component_id"))
