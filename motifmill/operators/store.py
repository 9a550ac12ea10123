"""The neighbourhood store: the data graph partitioned so that hub units are listed without a join of parts.

Long rows ``(part, center, a, b, kind)``: kind 0 is a star row (a = center, b a
neighbour), kind 1 an inner row (an edge a < b between two neighbours of center). The
local graph of a center is the rows with that center, and ``part`` is where it lives.
Rows of one center are spread over many rows, not packed, so a hub is no single value.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise

STAR, INNER = 0, 1


@dataclass(frozen=True)
class Partitioner:
    """Vertex to part: ``hash``, ``mod``, ``range`` (with the largest id) or an own SQL expression on ``v``."""

    m: int
    kind: str = "mod"
    top: int = 0
    expression: str = ""

    def part(self, v: Column) -> Column:
        if self.kind == "hash":
            return F.pmod(F.xxhash64(v), F.lit(self.m)).cast("int")
        if self.kind == "mod":
            return F.pmod(v, F.lit(self.m)).cast("int")
        if self.kind == "range":
            return (F.least(F.greatest(F.width_bucket(v.cast("double"), F.lit(0.0), F.lit(float(self.top + 1)), F.lit(self.m)), F.lit(1)), F.lit(self.m)) - 1).cast("int")
        return F.pmod(F.transform(F.array(v), lambda v: F.expr(self.expression))[0], F.lit(self.m)).cast("int")


def both_ways(edges: DataFrame) -> DataFrame:
    """(v, n) of each edge in both directions."""
    return edges.select(F.inline(F.array(F.struct(F.col("u").alias("v"), F.col("v").alias("n")), F.struct("v", F.col("u").alias("n")))))


def adjacency(edges: DataFrame) -> DataFrame:
    """(v, nbrs, deg): neighbours sorted."""
    return both_ways(edges).groupBy("v").agg(F.sort_array(F.collect_list("n")).alias("nbrs")).withColumn("deg", F.size("nbrs"))


def star_lists(store: DataFrame, deleted: DataFrame, added: DataFrame) -> DataFrame:
    """(v, nbrs, deg) of the vertices that an update touches, from the store's star rows: no scan of all edges, no list of others."""
    ends = both_ways(deleted.unionByName(added)).select(F.col("v").alias("center")).distinct()
    rows = store.where(F.col("kind") == STAR).join(ends, "center", "left_semi")
    return rows.groupBy(F.col("center").alias("v")).agg(F.sort_array(F.collect_list("b")).alias("nbrs")).withColumn("deg", F.size("nbrs"))


def degrees(edges: DataFrame) -> DataFrame:
    """(v, deg) without the lists."""
    return both_ways(edges).groupBy("v").agg(F.count("*").cast("int").alias("deg"))


def induced_subgraph(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends in ``vertices(v)``."""
    kept = vertices.select("v").distinct()
    return edges.join(kept.withColumnRenamed("v", "u"), "u", "left_semi").join(kept, "v", "left_semi").select("u", "v")


def edges_around(edges: DataFrame, ends: DataFrame, steps: int) -> DataFrame:
    """Edges that have an end within some steps of ``ends(v)``."""
    near = ends.select("v").distinct()
    for _ in range(steps):
        reached = both_ways(edges).join(near, "v", "left_semi").select(F.col("n").alias("v"))
        near = materialise(near.union(reached).distinct(), "near")
    by_u = edges.join(near.withColumnRenamed("v", "u"), "u", "left_semi").select("u", "v")
    return by_u.union(edges.join(near, "v", "left_semi").select("u", "v")).distinct()


def local_graph(edges: DataFrame, center: int) -> DataFrame:
    """What the graph has on a vertex and its neighbours."""
    around = both_ways(edges).where(F.col("v") == center).select(F.col("n").alias("v")).union(edges.sparkSession.range(1).select(F.lit(center).cast("bigint").alias("v")))
    return induced_subgraph(edges, around)


def is_connected(edges: DataFrame) -> bool:
    """Whether the graph is one component, by spreading least labels until nothing changes."""
    ends = materialise(both_ways(edges), "ends")
    label = ends.groupBy("v").agg(F.least(F.min("n"), F.first("v")).alias("l"))
    count = -1
    while True:
        now = label.agg(F.count_distinct("l"), F.sum("l")).first()
        if now[0] <= 1:
            return True
        if now == count:
            return False
        count = now
        spread = ends.join(label.withColumnRenamed("v", "n"), "n").groupBy("v").agg(F.min("l").alias("m"))
        label = materialise(spread.join(label, "v").select("v", F.least("m", "l").alias("l")), "labels")


def oriented(edges: DataFrame) -> DataFrame:
    """(x, y, dy): every edge from the end of lower (degree, id) to the other, with the degree of the latter."""
    d = degrees(edges)
    both = edges.join(d.select(F.col("v").alias("u"), F.col("deg").alias("du")), "u").join(d.withColumnRenamed("deg", "dv"), "v")
    low = F.struct("du", "u") < F.struct("dv", "v")
    return both.select(F.when(low, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(low, F.col("v")).otherwise(F.col("u")).alias("y"), F.greatest("du", "dv").alias("dy"))


def triangles(edges: DataFrame) -> DataFrame:
    """(x, y, z), each triangle once, x < y < z.

    Wedges open at the end of lowest degree, which has at most as many out-edges as the
    root of twice the edges, whatever the hubs are.
    """
    out = oriented(edges)
    wedge = out.select("x", "y", "dy").join(out.select("x", F.col("y").alias("z"), F.col("dy").alias("dz")), "x").where(F.struct("dy", "y") < F.struct("dz", "z"))
    closing = out.select(F.col("x").alias("y"), F.col("y").alias("z"))
    t = F.sort_array(F.array("x", "y", "z"))
    return wedge.join(closing, ["y", "z"]).select(t[0].alias("x"), t[1].alias("y"), t[2].alias("z"))


def star_rows(edges: DataFrame, h: Partitioner) -> DataFrame:
    return both_ways(edges).select(h.part(F.col("v")).alias("part"), F.col("v").alias("center"), F.col("v").alias("a"), F.col("n").alias("b"), F.lit(STAR).alias("kind"))


def build_store(edges: DataFrame, h: Partitioner, method: str = "triangle") -> DataFrame:
    """The store of a graph.

    ``triangle``: one inner row for each corner of a triangle. ``ship``: each vertex's
    list goes to all its neighbours, and what a neighbour shares with its own list is inner.
    """
    if method == "triangle":
        return store_rows(edges, triangles(edges), h)
    if method == "ship":
        adj = adjacency(edges)
        shipped = adj.select(F.explode("nbrs").alias("center"), F.col("v").alias("a"), "nbrs")
        own = adj.select(F.col("v").alias("center"), F.col("nbrs").alias("mine"))
        met = shipped.join(own, "center").select("center", "a", F.explode(F.array_intersect("nbrs", "mine")).alias("b"))
        inner = met.where("a < b")
    else:
        raise ValueError(method)
    return star_rows(edges, h).union(_inner_rows(inner, h))


def _inner_rows(inner: DataFrame, h: Partitioner) -> DataFrame:
    return inner.select(h.part(F.col("center")).alias("part"), "center", "a", "b", F.lit(INNER).alias("kind"))


def store_rows(edges: DataFrame, found: DataFrame, h: Partitioner) -> DataFrame:
    """The store of a graph whose triangles (x, y, z) are known: a plan over both that moves no row."""
    corners = F.array(*[F.struct(F.col(c).alias("center"), F.col(a).alias("a"), F.col(b).alias("b")) for c, a, b in ("xyz", "yxz", "zxy")])
    return star_rows(edges, h).union(_inner_rows(found.select(F.inline(corners)), h))


def merge_parts(store: DataFrame) -> DataFrame:
    """(part, a, b, a_center, b_center): distinct edges of each part, and which ends are its centers."""
    edges = store.select("part", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    centers = store.select("part", "center").distinct()
    ends = edges.join(centers.select("part", F.col("center").alias("a"), F.lit(True).alias("ca")), ["part", "a"], "left")
    ends = ends.join(centers.select("part", F.col("center").alias("b"), F.lit(True).alias("cb")), ["part", "b"], "left")
    return ends.select("part", "a", "b", F.coalesce("ca", F.lit(False)).alias("a_center"), F.coalesce("cb", F.lit(False)).alias("b_center"))


def pack(store: DataFrame) -> DataFrame:
    """(part, center, nbrs, inner array of (a, b)): one row a center, for centers of bounded degree."""
    inner = F.collect_list(F.when(F.col("kind") == INNER, F.struct("a", "b")))
    return store.groupBy("part", "center").agg(F.sort_array(F.collect_list(F.when(F.col("kind") == STAR, F.col("b")))).alias("nbrs"), F.sort_array(inner).alias("inner"))


def unpack(packed: DataFrame) -> DataFrame:
    star = packed.select("part", "center", F.col("center").alias("a"), F.explode("nbrs").alias("b"), F.lit(STAR).alias("kind"))
    return star.union(packed.select("part", "center", F.inline("inner"), F.lit(INNER).alias("kind")))


def save_store(store: DataFrame, name: str, buckets: int) -> DataFrame:
    """A table bucketed and sorted by center: joins on the center need no exchange when
    ``spark.sql.requireAllClusterKeysForCoPartition`` is false."""
    store.write.mode("overwrite").bucketBy(buckets, "center").sortBy("center").saveAsTable(name)
    return store.sparkSession.table(name)


# -- space -----------------------------------------------------------------------


def space_bound(edges: DataFrame, m: int) -> DataFrame:
    """(edges, triangles, bound): extra edges are at most min(3 triangles, (m - 1) edges)."""
    e, t = edges.agg(F.count("*").alias("edges")), triangles(edges).agg(F.count("*").alias("triangles"))
    return e.join(t).withColumn("bound", F.least(3 * F.col("triangles"), (m - 1) * F.col("edges")))


def space_actual(store: DataFrame, h: Partitioner) -> DataFrame:
    """(star, stored, extra): edges counted once for each part of their ends, edges of all merged parts, difference."""
    star = store.where(F.col("kind") == STAR).select(h.part(F.col("a")).alias("p"), F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).distinct().agg(F.count("*").alias("star"))
    stored = store.select("part", F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct().agg(F.count("*").alias("stored"))
    return star.join(stored).select("star", "stored", (F.col("stored") - F.col("star")).alias("extra"))


def part_sizes(store: DataFrame) -> DataFrame:
    return merge_parts(store).groupBy("part").agg(F.count("*").alias("edges"))


# -- update ------------------------------------------------------------------------


def normalize_update(edges: DataFrame, update: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Effective (deleted, added) of raw ``(op, u, v)``: deletes of edges that are there, then inserts of edges that
    are not there afterwards; loops, repeats and pairs of both ops on an edge fall away or cancel out."""
    ops = update.where("u <> v").select("op", F.least("u", "v").cast("bigint").alias("u"), F.greatest("u", "v").cast("bigint").alias("v"))
    gone, come = ops.where("op = '-'").select("u", "v").distinct(), ops.where("op = '+'").select("u", "v").distinct()
    deleted = gone.join(come, ["u", "v"], "left_anti").join(edges, ["u", "v"], "left_semi")
    added = come.join(edges, ["u", "v"], "left_anti")
    return deleted, added


def delete_vertices(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """The update (op, u, v) that deletes vertices: their edges go."""
    v = vertices.select("v").distinct()
    touched = edges.join(v.withColumnRenamed("v", "u"), "u", "left_semi").union(edges.join(v, "v", "left_semi").select("u", "v"))
    return touched.distinct().select(F.lit("-").alias("op"), "u", "v")


def updated_edges(edges: DataFrame, deleted: DataFrame, added: DataFrame) -> DataFrame:
    return edges.join(deleted, ["u", "v"], "left_anti").select("u", "v").union(added.select("u", "v"))


def updated_neighbours(adj: DataFrame, deleted: DataFrame, added: DataFrame) -> DataFrame:
    """(v, nbrs, deg) of vertices that an update touches, after it; new vertices too, isolated ones with no neighbours."""
    lists = lambda e, name: both_ways(e).groupBy("v").agg(F.collect_list("n").alias(name))
    touched = lists(deleted, "gone").join(lists(added, "come"), "v", "full")
    empty = F.array().cast("array<bigint>")
    of = touched.join(adj.select("v", "nbrs"), "v", "left")
    now = F.array_union(F.array_except(F.coalesce("nbrs", empty), F.coalesce("gone", empty)), F.coalesce("come", empty))
    return of.select("v", F.sort_array(now).alias("nbrs")).withColumn("deg", F.size("nbrs"))


@dataclass(frozen=True)
class StoreDelta:
    """Rows to drop from and rows to add to a store."""

    dropped: DataFrame
    inserted: DataFrame


def delta_store(store: DataFrame, adj: DataFrame, deleted: DataFrame, added: DataFrame, h: Partitioner) -> StoreDelta:
    """What an update changes.

    A deleted (x, y) takes its star rows, its inner rows at every center, and what x has
    about y and y about x. An inserted (x, y) adds star rows, and for every common new
    neighbour z the three inner rows of that triangle. Both sides only need rows and
    lists around the update, so the joins carry the update, not the store.
    """
    inner, star = store.where(F.col("kind") == INNER), store.where(F.col("kind") == STAR)
    gone = both_ways(deleted)
    edge = inner.join(deleted.select(F.col("u").alias("a"), F.col("v").alias("b")), ["a", "b"], "left_semi")
    about = [inner.join(gone.select(F.col("v").alias("center"), F.col("n").alias(c)), ["center", c], "left_semi") for c in "ab"]
    stars = star.join(gone.select(F.col("v").alias("a"), F.col("n").alias("b")), ["a", "b"], "left_semi")
    names = ["part", "center", "a", "b", "kind"]
    dropped = stars.select(names).union(edge.select(names)).union(about[0].select(names)).union(about[1].select(names)).distinct()
    touched = updated_neighbours(adj, deleted, added).select("v", "nbrs")
    ends = added.join(touched.select(F.col("v").alias("u"), F.col("nbrs").alias("nu")), "u").join(touched.withColumnRenamed("nbrs", "nv"), "v")
    z = ends.select("u", "v", F.explode(F.array_intersect("nu", "nv")).alias("z"))
    corner = lambda c, a, b: F.struct(F.col(c).alias("center"), F.least(a, b).alias("a"), F.greatest(a, b).alias("b"))
    new = z.select(F.inline(F.array(corner("z", "u", "v"), corner("u", "v", "z"), corner("v", "u", "z")))).distinct()
    inserted = star_rows(added, h).union(new.select(h.part(F.col("center")).alias("part"), "center", "a", "b", F.lit(INNER).alias("kind")))
    return StoreDelta(dropped, inserted)


def apply_delta(store: DataFrame, delta: StoreDelta, mode: str = "merge") -> DataFrame:
    """``merge``: the changed store as a plan; ``touched``: only the rows of parts that change, for overwriting those parts."""
    if mode == "touched":
        parts = delta.dropped.select("part").union(delta.inserted.select("part")).distinct()
        store = store.join(parts, "part", "left_semi").select(store.columns)
    elif mode != "merge":
        raise ValueError(mode)
    return store.join(delta.dropped, ["center", "a", "b", "kind"], "left_anti").select(store.columns).union(delta.inserted.select(store.columns))


def update_store(store: DataFrame, adj: DataFrame, deleted: DataFrame, added: DataFrame, h: Partitioner) -> DataFrame:
    return apply_delta(store, delta_store(store, adj, deleted, added, h))


def update_cases(deleted: DataFrame, added: DataFrame, h: Partitioner) -> DataFrame:
    """(op, part, u, v, case): what an edge is to a part that holds an end or both: center-center, center-border."""
    ops = deleted.select(F.lit("-").alias("op"), "u", "v").union(added.select(F.lit("+").alias("op"), "u", "v"))
    pu, pv = h.part(F.col("u")), h.part(F.col("v"))
    return ops.select("op", "u", "v", F.explode(F.array_distinct(F.array(pu, pv))).alias("part"), F.when(pu == pv, "center-center").otherwise("center-border").alias("case"))


def update_messages(adj: DataFrame, deleted: DataFrame, added: DataFrame) -> DataFrame:
    """(vertices, shipped, bound): touched vertices, integers of their new lists, and the bound of three times that."""
    touched = updated_neighbours(adj, deleted, added)
    return touched.agg(F.count("*").alias("vertices"), F.coalesce(F.sum("deg"), F.lit(0)).cast("bigint").alias("shipped"), F.coalesce(3 * F.sum("deg"), F.lit(0)).cast("bigint").alias("bound"))


# -- bitmaps --------------------------------------------------------------------------


def partition_bitmaps(edges: DataFrame, h: Partitioner) -> DataFrame:
    """(v, words): bit k % 32 of word k // 32 is set if part k is the home of a neighbour of v."""
    words = (h.m + 31) // 32
    parts = both_ways(edges).select("v", h.part(F.col("n")).alias("p"))
    bit = lambda k: F.bit_or(F.when(F.floor(F.col("p") / 32) == k, F.expr("shiftleft(1, p % 32)")).otherwise(0)).cast("int")
    return parts.groupBy("v").agg(F.array(*[bit(k) for k in range(words)]).alias("words"))


def parts_of_bitmap(words: Column, m: int) -> Column:
    """Parts whose bits are set."""
    parts = F.sequence(F.lit(0), F.lit(m - 1))
    return F.filter(parts, lambda p: F.getbit(F.element_at(words, (F.floor(p / 32) + 1).cast("int")).cast("bigint").bitwiseAND(F.lit(0xFFFFFFFF)), p % 32) == 1)
