"""Near copies: SimHash first, then the Jaccard similarity of word shingles, 0.8 and more.

Search: every text has the SimHash fingerprint of its shingles, and the Gray-order tree of
``simhash`` finds all fingerprints within three bits of each other. Copies that lie
further apart share one of ``BANDS`` keys of ``ROWS`` minima each, over the XXH64 values of
a text's shingles: a pair at similarity s shares no key with probability
``(1 - s^ROWS)^BANDS``, 1.2e-7 at 0.8. Every member of a key's bucket is linked to the
least one, so links grow with the buckets and not with their squares. Texts that either
search joins fall into one cluster.

Check: exactly the pairs of a cluster are linked whose sets of shingles are similar by 0.8
and more, however they were found. Postings of shingles give the overlaps; texts that have
found their group leave the postings. A cluster of more than ``BLOCK`` texts is dealt into
blocks. First each block meets alone, with ``PIVOTS`` texts of the cluster that all its
blocks see, so copies of one text become one group in a pass over the cluster. Texts
outside the largest group of a cluster then meet all others, again in blocks, and
only links between groups come out of that: members of the same group are not compared
again, and no task holds more than two blocks whatever the cluster's size.

Texts, not ids, are the nodes of clusters and groups: ids may repeat with other texts.

Nulls: a text without words is a copy of other such texts only; rows without an id are
near copies of nothing and stay. Rows that repeat an id with other texts are judged each;
of rows that repeat id and words one stays, the one whose text is least. A very long text
is one set of shingles. An empty table gives an empty result. Input columns may have any
names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, StructField, StructType

from motifmill.functions.scratch import materialise
from motifmill.llm.components import star_components
from motifmill.llm.simhash import SEED, majority, shingle_hashes, similar_links
from motifmill.llm.words import byte_slices, raw_texts

#: The least similarity of near copies, as a fraction.
NUMERATOR, DENOMINATOR = 4, 5
BANDS, ROWS = 40, 5
#: Postings that a task gathers at once.
GATHER = 1 << 22
#: Texts of a cluster that meet in one task as they are.
BLOCK = 512
#: Texts of a large cluster that meet every block.
PIVOTS = 16
#: Bytes of ids up to which they are broadcast, so that texts that have no part in a join stay where they are.
IDS_BROADCAST = 32 << 20

_RNG = np.random.default_rng(SEED)
_FACTORS = (_RNG.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32) | np.uint32(1))[:, None]
_MASKS = _RNG.integers(0, 1 << 32, BANDS * ROWS, dtype=np.uint32)[:, None]


def band_keys(hashes: np.ndarray) -> np.ndarray:
    """The keys of a text's bands, from the 64-bit values of its shingles."""
    short = (hashes ^ (hashes >> np.uint64(32))).astype(np.uint32)
    low = np.full(BANDS * ROWS, 0xFFFFFFFF, dtype=np.uint32)
    for at in range(0, len(short), 512):
        np.minimum(low, ((short[at : at + 512] ^ _MASKS) * _FACTORS).min(axis=1), out=low)
    keys = np.arange(1, BANDS + 1, dtype=np.uint64)
    for column in low.reshape(BANDS, ROWS).T:
        keys = (keys ^ column) * np.uint64(0x9E3779B97F4A7C15)
        keys ^= keys >> np.uint64(29)
    return keys.view(np.int64)


def sketches(docs: DataFrame, width: int, text: str, key: str) -> DataFrame:
    """(key, digest of the words, SimHash fingerprint, keys of the bands); a text without words has no bands."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in byte_slices(batches, 1, 4 << 20):
            digests, codes, keys, ends = [], [], [np.zeros(0, np.int64)], [0]
            for raw in raw_texts(batch.column(1)):
                hashes = shingle_hashes(raw, width)
                digests.append(xxhash.xxh3_128_digest(b" ".join(raw.lower().split())))
                codes.append(majority(hashes))
                if len(hashes):
                    keys.append(band_keys(hashes))
                ends.append(ends[-1] + (BANDS if len(hashes) else 0))
            bands = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(keys)))
            codes = pa.array(np.array(codes, dtype=np.uint64).view(np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(digests, pa.binary()), codes, bands], ["key", "digest", "fp", "bands"])

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(run, f"key {kind}, digest binary, fp bigint, bands array<bigint>")


def _bucket_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (band, root) sorted by both; yields a link from each member of a bucket to its first."""
    band = first = None
    for batch in batches:
        bands, roots = (c.to_numpy() for c in batch.columns)
        if not len(bands):
            continue
        new = np.append(True, bands[1:] != bands[:-1])
        at = np.flatnonzero(new)
        firsts = roots[at]
        if band == bands[0]:
            firsts[0] = first
        leader = firsts[np.cumsum(new) - 1]
        band, first = bands[-1], leader[-1]
        found = roots != leader
        yield pa.RecordBatch.from_arrays([pa.array(roots[found]), pa.array(leader[found])], ["u", "v"])


class Postings:
    """Shingles of the texts that have no group yet."""

    def __init__(self, sets: list[np.ndarray]):
        self.n = len(sets)
        who = np.repeat(np.arange(self.n), [len(s) for s in sets])
        flat = np.concatenate(sets)
        order = np.argsort(flat, kind="stable")
        self.flat, self.who = flat[order], who[order]

    def keep(self, wanted: np.ndarray) -> None:
        left = wanted[self.who]
        self.flat, self.who = self.flat[left], self.who[left]

    def overlaps(self, shingles: np.ndarray) -> np.ndarray:
        """How many of the shingles each text has."""
        lo = np.searchsorted(self.flat, shingles, "left")
        size = np.searchsorted(self.flat, shingles, "right") - lo
        lo, size = lo[size > 0], size[size > 0]
        ends = np.cumsum(size)
        out = np.zeros(self.n, dtype=np.int64)
        start = 0
        while start < len(size):
            done = int(ends[start - 1]) if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, done + GATHER, side="right")))
            part = size[start:stop]
            at = np.repeat(lo[start:stop] - (ends[start:stop] - part - done), part) + np.arange(int(part.sum()))
            out += np.bincount(self.who[at], minlength=self.n)
            start = stop
        return out


def similar_groups(sets: list[np.ndarray]) -> np.ndarray:
    """For each set of shingles, the place of the first of its group: the components of the pairs similar by 0.8 and more."""
    sizes = np.array([len(s) for s in sets])
    label = np.full(len(sets), -1)
    posts, held = Postings(sets), len(sets)
    for root in range(len(sets)):
        if label[root] >= 0:
            continue
        label[root] = root
        stack = [root]
        while stack:
            left = label < 0
            n = int(left.sum())
            if not n:
                return label
            if 2 * n <= held:
                posts.keep(left)
                held = n
            one = stack.pop()
            both = posts.overlaps(sets[one])
            found = np.flatnonzero(left & (DENOMINATOR * both >= NUMERATOR * (sizes + sizes[one] - both)))
            label[found] = root
            stack += found.tolist()
    return label


def cross_links(sets: list[np.ndarray], groups: list[int], loose: list[bool]) -> list[tuple[int, int]]:
    """Links (larger, smaller) that join the groups of sets similar by 0.8 and more; only ``loose`` sets are compared with others."""
    names, at = np.unique(np.array(groups), return_inverse=True)
    parent = np.arange(len(names))
    sizes = np.array([len(s) for s in sets])
    posts, out = Postings(sets), []
    for one in np.flatnonzero(loose):
        label = parent[at]
        if (label == label[one]).all():
            continue
        both = posts.overlaps(sets[one])
        near = np.unique(label[DENOMINATOR * both >= NUMERATOR * (sizes + sizes[one] - both)])
        near = np.union1d(near, label[one : one + 1])
        if len(near) > 1:
            out += [(int(names[x]), int(names[near[0]])) for x in near[1:]]
            parent[np.isin(parent, near)] = near[0]
    return out


def _meeting_links(width: int, cross: bool):
    """Rows (meeting, node, group, loose, text) sorted by meeting and node; yields links that span the groups found.

    Texts of a meeting have no groups yet, or, with ``cross``, only links between their groups are wanted.
    """

    def links(nodes: list[int], groups: list[int], loose: list[bool], sets: list[np.ndarray]) -> list[tuple[int, int]]:
        if cross:
            return cross_links(sets, groups, loose)
        return [(nodes[k], nodes[x]) for k, x in enumerate(similar_groups(sets)) if k != x]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, ([], [], [], [])
        for batch in byte_slices(batches, 4, 4 << 20):
            found = []
            *columns, texts = batch.columns
            for m, node, group, loose, raw in zip(*[c.to_pylist() for c in columns], raw_texts(texts), strict=True):
                if m != now:
                    found += links(*held) if held[0] else []
                    now, held = m, ([], [], [], [])
                for x, into in zip((node, group, loose, np.unique(shingle_hashes(raw, width))), held, strict=True):
                    into.append(x)
            yield _link_batch(found)
        if held[0]:
            yield _link_batch(links(*held))

    return run


def _link_batch(found: list[tuple[int, int]]) -> pa.RecordBatch:
    u, v = zip(*found, strict=True) if found else ((), ())
    return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], ["u", "v"])


def _small(ids: DataFrame) -> DataFrame:
    """A written table of ids, to be broadcast if its measured size allows it; beyond that Spark chooses the join."""
    return F.broadcast(ids) if ids.count() * 16 * len(ids.columns) <= IDS_BROADCAST else ids


def _blocks(size: Column, block: int) -> Column:
    return F.ceil(size / block).cast("int")


def _block_of(blocks: Column) -> Column:
    return F.pmod(F.xxhash64("node"), blocks).cast("int")


def _meet(rows: DataFrame, width: int, cross: bool) -> DataFrame:
    """Links of rows (component, i, j, node, group, loose, text), each (component, i, j) a meeting."""
    dealt = rows.select(F.xxhash64("component", "i", "j").alias("meeting"), "node", "group", "loose", "text")
    return dealt.repartition("meeting").sortWithinPartitions("meeting", "node").mapInArrow(_meeting_links(width, cross), "u bigint, v bigint")


def _exact_groups(members: DataFrame, clusters: DataFrame, width: int, block: int) -> DataFrame:
    """(node, component): the groups within clusters, from texts ``members(component, node, text)``."""
    sizes = clusters.groupBy("component").agg(F.count("*").alias("size"))
    large = materialise(sizes.where(F.col("size") > block).select(F.col("component").alias("c"), _blocks(F.col("size"), block).alias("blocks")), "large-clusters")
    plain = members.select("component", F.lit(0).alias("i"), F.lit(0).alias("j"), "node", F.lit(0).cast("bigint").alias("group"), F.lit(True).alias("loose"), "text")
    if large.isEmpty():
        return star_components(_meet(plain, width, False))
    # a cluster's pivots are the least nodes of parts of it; they meet every block
    least = clusters.join(_small(large), F.col("component") == F.col("c")).select("component", "node", "blocks")
    picked = least.groupBy("component", "blocks", F.pmod(F.xxhash64("node", F.lit(1)), F.lit(PIVOTS)).alias("k")).agg(F.min("node").alias("p"))
    pivots = _small(materialise(picked.select("p", F.col("blocks").alias("b")), "pivots"))
    own = plain.join(_small(large), F.col("component") == F.col("c"), "left").withColumn("i", F.when(F.col("blocks").isNull(), 0).otherwise(_block_of(F.col("blocks"))))
    own = own.join(pivots, F.col("node") == F.col("p"), "left")
    seen = F.when(F.col("b").isNull(), F.array("i")).otherwise(F.sequence(F.lit(0), F.col("b") - 1))
    first = _meet(own.withColumn("i", F.explode(seen)), width, False)
    groups = materialise(star_components(first), "block-groups")

    # the largest group of each large cluster is settled in itself; all other texts meet every text of the cluster
    found = least.join(groups.withColumnRenamed("component", "g"), "node", "left").select("component", "node", F.coalesce("g", "node").alias("group"))
    found = materialise(found, "found-groups")
    count = found.groupBy("component", "group").agg(F.count("*").alias("n"))
    main = count.groupBy("component").agg(F.max_by("group", F.struct("n", "group")).alias("main"), F.max("n").alias("m"), F.sum("n").alias("n"))
    main = main.where(F.col("n") > F.col("m")).select(F.col("component").alias("c"), "main", _blocks(F.col("m"), block).alias("inner"), _blocks(F.col("n") - F.col("m"), block).alias("outer"))
    main = materialise(main, "main-groups")
    if main.isEmpty():
        return groups
    roles = found.join(_small(main), F.col("component") == F.col("c")).select(F.col("node").alias("p"), "group", (F.col("group") != F.col("main")).alias("loose"), "inner", "outer")
    met = members.join(_small(materialise(roles, "roles")), F.col("node") == F.col("p"))
    mine = F.when(F.col("loose"), _block_of(F.col("outer"))).otherwise(F.col("outer") + _block_of(F.col("inner")))
    met = met.withColumn("mine", mine)
    # a block of the main group meets all outer blocks; an outer block meets all blocks
    others = F.sequence(F.lit(0), F.when(F.col("loose"), F.col("outer") + F.col("inner")).otherwise(F.col("outer")) - 1)
    met = met.withColumn("other", F.explode(others)).select("component", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "node", "group", "loose", "text")
    joined = star_components(_meet(met, width, True))
    joined = joined.select(F.col("node").alias("g"), F.col("component").alias("to"))
    every = groups.select("node", F.col("component").alias("group")).union(found.where(F.col("node") == F.col("group")).select("node", "group")).distinct()
    return every.join(joined, F.col("group") == F.col("g"), "left").select("node", F.coalesce("to", "group").alias("component"))


def near_copy_components(docs: DataFrame, width: int = 5, text: str = "text", key: str = "doc_id", block: int = BLOCK) -> DataFrame:
    """(key, digest, component, first): the words' digest, the group over texts of equal words and pairs similar by 0.8 and
    more, and the least (key, digest) of the group."""
    own = materialise(sketches(docs, width, text, key), "sketches")
    texts = own.groupBy("digest").agg(F.min("key").alias("least"), F.first("fp").alias("fp"), F.first("bands").alias("bands"))
    texts = materialise(texts.withColumn("root", F.monotonically_increasing_id()), "texts")
    rows = texts.select(F.explode("bands").alias("band"), "root").repartition("band").sortWithinPartitions("band", "root")
    # texts with one fingerprint are linked to the least of them, which stands for it in the Gray tree
    coded = texts.where(F.size("bands") > 0).select("fp", "root")
    codes = materialise(coded.groupBy("fp").agg(F.min("root").alias("root")), "codes")
    same = coded.join(codes.select(F.col("fp").alias("__fp"), F.col("root").alias("v")), F.col("fp") == F.col("__fp")).where(F.col("root") != F.col("v")).select(F.col("root").alias("u"), "v")
    links = similar_links(codes).union(same).union(rows.mapInArrow(_bucket_links, "u bigint, v bigint"))
    clusters = materialise(star_components(links), "clusters")
    # one row of each text of a cluster: the least key's, by a digest that the sketch has already
    linked = materialise(texts.join(clusters, F.col("root") == F.col("node")).select(F.col("least").alias("__k"), F.col("digest").alias("__d"), "node", "component"), "linked")
    known = _small(linked)
    raw = docs.select(F.col(key).alias("key"), F.col(text).alias("text")).join(_small(materialise(linked.select(F.col("__k").alias("key")).distinct(), "members")), "key", "left_semi")
    seen = raw.mapInArrow(_digested, f"key {docs.schema[key].dataType.simpleString()}, digest binary, text string")
    members = seen.join(known, (F.col("key") == F.col("__k")) & (F.col("digest") == F.col("__d"))).select("component", "node", "text")
    labels = _exact_groups(members, clusters, width, block)
    classes = texts.join(labels, F.col("root") == F.col("node"), "left").select("digest", "least", F.coalesce("component", "root").alias("component"))
    classes = materialise(classes, "classes")
    firsts = classes.groupBy("component").agg(F.min(F.struct(F.col("least").alias("key"), "digest")).alias("first"))
    grouped = classes.join(firsts, "component").select(F.col("digest").alias("of"), "component", "first")
    return own.join(grouped, F.col("digest") == F.col("of")).select("key", "digest", "component", "first")


def _digested(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, text) with the digest of the text's words."""
    for batch in byte_slices(batches, 1, 4 << 20):
        digests = [xxhash.xxh3_128_digest(b" ".join(raw.lower().split())) for raw in raw_texts(batch.column(1))]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(digests, pa.binary()), batch.column(1)], ["key", "digest", "text"])


def keep_one_of_each(docs: DataFrame, width: int = 5, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row of each group of near copies, the one with the least id, with the columns of ``docs``.

    Ids that come once, which is the rule, decide by the id alone and no text is looked at again. Rows that share an id
    are told apart by the digest of their words, and rows equal in both by the order of the text.
    """
    own = docs.where(F.col(key).isNotNull())
    groups = materialise(near_copy_components(own, width, text, key), "near-copies")
    lost = docs.where(F.col(key).isNull())
    repeated = materialise(groups.groupBy("key").count().where("count > 1").select(F.col("key").alias("__id")), "repeated-ids")
    gone = groups.where((F.col("key") != F.col("first.key")) | (F.col("digest") != F.col("first.digest"))).select(F.col("key").alias("__id"))
    unlike = _small(materialise(gone.union(repeated).distinct(), "gone"))
    plain = own.join(unlike, own[key] == F.col("__id"), "left_anti")
    if repeated.isEmpty():
        return plain.unionAll(lost)
    mixed = own.join(repeated, own[key] == F.col("__id"), "left_semi")
    wide = mixed.select(F.col(key).alias("key"), F.col(text).alias("text"), F.struct(*[F.col(c) for c in docs.columns]).alias("row"))
    marked = wide.mapInArrow(_digested_rows, StructType([wide.schema["key"], StructField("digest", BinaryType()), wide.schema["row"]]))
    kept = groups.where((F.col("key") == F.col("first.key")) & (F.col("digest") == F.col("first.digest"))).select(F.col("key").alias("__k"), F.col("digest").alias("__d"))
    stay = marked.join(kept, (F.col("key") == F.col("__k")) & (F.col("digest") == F.col("__d")), "left_semi")
    best = stay.groupBy("key", "digest").agg(F.min("row").alias("row")).select("row.*").select(*docs.columns)
    return plain.unionAll(best).unionAll(lost)


def _digested_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in byte_slices(batches, 1, 4 << 20):
        digests = [xxhash.xxh3_128_digest(b" ".join(raw.lower().split())) for raw in raw_texts(batch.column(1))]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(digests, pa.binary()), batch.column(2)], ["key", "digest", "row"])
