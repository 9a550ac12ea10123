"""Rival methods, rebuilt to compare with, and the brute force that checks all."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise
from motifmill.operators.compress import all_of, clean_sets, free, kept, pair_condition
from motifmill.operators.join import plain_join
from motifmill.operators.store import adjacency, both_ways, oriented, triangles, updated_edges
from motifmill.plans.estimate import Sizes
from motifmill.plans.pattern import Order, Pattern, is_clique, pick_anchor
from motifmill.plans.planner import Tree, optimal_tree


def list_cliques(edges: DataFrame, k: int) -> DataFrame:
    """(v1 .. vk), each clique once in ascending order of degree and id: a clique is extended by common out-neighbours."""
    out = oriented(edges).select("x", "y")
    cliques = out.select(F.col("x").alias("v1"), F.col("y").alias("v2"))
    for size in range(3, k + 1):
        grown = cliques.join(out.select(F.col("x").alias(f"v{size - 1}"), F.col("y").alias(f"v{size}")), f"v{size - 1}")
        for j in range(1, size - 1):
            grown = grown.join(out.select(F.col("x").alias(f"v{j}"), F.col("y").alias(f"v{size}")), [f"v{j}", f"v{size}"], "left_semi")
        cliques = grown.select(*[f"v{j}" for j in range(1, size + 1)])
    return cliques


def clique_index(edges: DataFrame, k0: int = 3) -> dict[int, DataFrame]:
    """All cliques of 2 to k0 vertices, by size."""
    return {k: list_cliques(edges, k) for k in range(2, k0 + 1)}


def index_ints(index: dict[int, DataFrame]) -> int:
    """Integers that the index stores."""
    return sum(k * rows.count() for k, rows in index.items())


class StarCliqueBaseline:
    """Units are stars and cliques of at most k0 vertices, matches are plain, the tree is the best bushy one."""

    def __init__(self, k0: int = 3):
        self.k0 = k0

    def prepare(self, edges: DataFrame) -> dict[int, DataFrame]:
        return clique_index(edges, self.k0)

    def plan(self, p: Pattern, sizes: Sizes) -> Tree:
        return optimal_tree(p, sizes, None, "stars+cliques", max_clique=self.k0)

    def _leaf(self, index: dict[int, DataFrame], q: Pattern, order: Order) -> DataFrame:
        if is_clique(q) and len(q.vertices) > 2:
            rows, k = index[len(q.vertices)], len(q.vertices)
            from itertools import permutations

            ways = F.array(*[F.struct(*[F.col(f"v{i + 1}").alias(f"f_{v}") for i, v in zip(way, q.vertices, strict=True)]) for way in permutations(range(k))])
            rows = rows.select(F.inline(ways))
        else:
            center = pick_anchor(q)
            ends = both_ways(index[2].select(F.col("v1").alias("u"), F.col("v2").alias("v")))
            rows, done = None, [center]
            for v in [w for w in q.vertices if w != center]:
                step = ends.select(F.col("v").alias(f"f_{center}"), F.col("n").alias(f"f_{v}"))
                rows = step if rows is None else rows.join(step, f"f_{center}")
                rows = rows.where(all_of([pair_condition(w, v, F.col(f"f_{w}"), F.col(f"f_{v}"), order) for w in done]))
                done.append(v)
        checks = [pair_condition(x, y, F.col(f"f_{x}"), F.col(f"f_{y}"), order) for k, x in enumerate(q.vertices) for y in q.vertices[k + 1 :]]
        return rows.where(all_of(checks)).select(*[f"f_{v}" for v in q.vertices])

    def list(self, index: dict[int, DataFrame], p: Pattern, order: Order, tree: Tree) -> DataFrame:
        if tree.left is None:
            return self._leaf(index, tree.piece, order)
        left, right = (self.list(index, p, order, t) for t in (tree.left, tree.right))
        return plain_join(left, right, tree.left.piece, tree.right.piece, order)


class CliqueIndexBaseline:
    """The core, a least connected cover, is matched first over stored edges and triangles; every other vertex is filled with
    the intersection of stored neighbour sets; output is compressed by the core."""

    def __init__(self, k0: int = 3):
        self.k0 = k0

    def prepare(self, edges: DataFrame) -> dict[int, DataFrame]:
        return clique_index(edges, self.k0)

    def core(self, p: Pattern) -> frozenset[str]:
        from motifmill.plans.pattern import vertex_covers

        return vertex_covers(p, connected=True)[0]

    def list(self, index: dict[int, DataFrame], p: Pattern, order: Order) -> tuple[DataFrame, frozenset[str]]:
        core = self.core(p)
        edges = index[2].select(F.col("v1").alias("u"), F.col("v2").alias("v"))
        ends = both_ways(edges)
        todo = kept(p, core)
        first = max(todo, key=p.degree)
        out, done = ends.select(F.col("v").alias(f"s_{first}")).distinct(), [first]
        while len(done) < len(todo):
            v = max((w for w in todo if w not in done), key=lambda w: len(p.neighbours[w] & set(done)))
            near, more = sorted(p.neighbours[v] & set(done))[0], sorted(p.neighbours[v] & set(done))[1:]
            out = out.join(ends.select(F.col("v").alias(f"s_{near}"), F.col("n").alias(f"s_{v}")), f"s_{near}")
            for w in more:
                out = out.join(ends.select(F.col("v").alias(f"s_{w}"), F.col("n").alias(f"s_{v}")), [f"s_{w}", f"s_{v}"], "left_semi")
            out = out.where(all_of([pair_condition(w, v, F.col(f"s_{w}"), F.col(f"s_{v}"), order) for w in done]))
            done.append(v)
        lists = adjacency(edges).select("v", "nbrs")
        corners = None
        for y in free(p, core):
            near = sorted(p.neighbours[y])
            pair = next(((a, b) for k, a in enumerate(near) for b in near[k + 1 :] if p.has(a, b)), None)
            sets = []
            if pair and 3 in index:  # the triangle table holds what both ends of an edge have in common
                if corners is None:
                    t = index[3]
                    ways = F.array(*[F.struct(F.least(a, b).alias("u"), F.greatest(a, b).alias("v"), F.col(c).alias("n")) for a, b, c in (("v1", "v2", "v3"), ("v1", "v3", "v2"), ("v2", "v3", "v1"))])
                    corners = t.select(F.inline(ways)).groupBy("u", "v").agg(F.sort_array(F.collect_list("n")).alias("l"))
                a, b = pair
                named = corners.select(F.col("u").alias("__u"), F.col("v").alias("__v"), F.col("l").alias("__t"))
                out = out.join(named, (F.least(f"s_{a}", f"s_{b}") == F.col("__u")) & (F.greatest(f"s_{a}", f"s_{b}") == F.col("__v"))).drop("__u", "__v")
                sets.append("__t")
                near = [w for w in near if w not in pair]
            for k, w in enumerate(near):
                out = out.join(lists.select(F.col("v").alias(f"s_{w}"), F.col("nbrs").alias(f"__l{k}")), f"s_{w}")
                sets.append(f"__l{k}")
            found = F.col(sets[0])
            for s in sets[1:]:
                found = F.array_intersect(found, F.col(s))
            out = out.withColumn(f"c_{y}", F.sort_array(found)).drop(*sets)
        out = out.select(*[f"s_{v}" for v in kept(p, core)], *[f"c_{v}" for v in free(p, core)])
        return clean_sets(out, p, core, order), core


class DeltaQueryBaseline:
    """One query for each pattern edge: that edge takes the update's edges, lower edges the new graph, higher ones the old;
    the match grows by a vertex at a time from a bound neighbour's list, checked against the others."""

    def _query(self, p: Pattern, order: Order, slot: int, delta: DataFrame, before: DataFrame, after: DataFrame) -> DataFrame:
        x, y = p.edges[slot]
        rows = both_ways(delta).select(F.col("v").alias(f"f_{x}"), F.col("n").alias(f"f_{y}"))
        rows = rows.where(pair_condition(x, y, F.col(f"f_{x}"), F.col(f"f_{y}"), order))
        done = [x, y]
        side = {e: (before if k < slot else after) for k, e in enumerate(p.edges)}
        while len(done) < len(p.vertices):
            v = max((w for w in p.vertices if w not in done), key=lambda w: len(p.neighbours[w] & set(done)))
            for k, w in enumerate(sorted(p.neighbours[v] & set(done))):
                ends = side[tuple(sorted((v, w)))].select(F.col("v").alias(f"f_{w}"), F.col("n").alias(f"f_{v}"))
                rows = rows.join(ends, [f"f_{w}", f"f_{v}"], "left_semi") if k else rows.join(ends, f"f_{w}")
            rows = rows.where(all_of([pair_condition(w, v, F.col(f"f_{w}"), F.col(f"f_{v}"), order) for w in done]))
            done.append(v)
        return rows.select(*[f"f_{v}" for v in p.vertices])

    def update(self, edges: DataFrame, deleted: DataFrame, added: DataFrame, p: Pattern, order: Order) -> DataFrame:
        """(sign, f_...): matches that come (+1) and go (-1)."""
        middle = edges.join(deleted, ["u", "v"], "left_anti").select("u", "v")
        old, mid, new = both_ways(edges), both_ways(middle), both_ways(updated_edges(edges, deleted, added))
        out = None
        for slot in range(len(p.edges)):
            # inserted: lower edges among the kept ones, higher ones in the new graph; deleted: the mirror image on the old graph
            for sign, delta, side in ((1, added, new), (-1, deleted, old)):
                part = self._query(p, order, slot, delta, mid, side).withColumn("sign", F.lit(sign))
                out = part if out is None else out.unionByName(part)
        return out.select("sign", *[f"f_{v}" for v in p.vertices])


def patch_bushy(store: DataFrame, old: DataFrame, p: Pattern, order: Order, tree: Tree, added: DataFrame, cover: frozenset[str]) -> DataFrame:
    """New matches by a bushy tree: at each node, new left with all right, and old left with new right; plain rows.

    All and new matches of a node are written once, as the node above reads each of them twice and more.
    """
    from motifmill.operators.compress import decompress
    from motifmill.operators.incremental import is_new
    from motifmill.operators.listing import list_unit_compressed
    from motifmill.plans.pattern import restrict

    def walk(t: Tree, root: bool = False) -> tuple[DataFrame | None, DataFrame]:
        if t.left is None:
            q = t.piece
            every = decompress(list_unit_compressed(store, q, cover, order), q, cover & set(q.vertices), restrict(order, q.vertices))
            every = materialise(every, "bushy-all")
            new = is_new(every, q, added)
            return every, new if root else materialise(new, "bushy-new")
        (al, nl), (ar, nr) = walk(t.left), walk(t.right)
        kept_left = al.exceptAll(nl)
        new = plain_join(nl, ar, t.left.piece, t.right.piece, order).unionByName(plain_join(kept_left, nr, t.left.piece, t.right.piece, order))
        if root:
            return None, new
        return materialise(plain_join(al, ar, t.left.piece, t.right.piece, order), "bushy-all"), materialise(new, "bushy-new")

    return walk(tree, True)[1]


def list_centralised(edges: DataFrame, p: Pattern, order: Order) -> DataFrame:
    """All matches by backtracking in a single task: what one machine does."""
    import pyarrow as pa

    names = [f"f_{v}" for v in p.vertices]
    steps = list(p.vertices)
    steps = [max(steps, key=p.degree)]
    while len(steps) < len(p.vertices):
        steps.append(max((v for v in p.vertices if v not in steps), key=lambda v: len(p.neighbours[v] & set(steps))))

    def run(batches):
        adj: dict[int, set[int]] = {}
        for b in batches:
            for u, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                adj.setdefault(u, set()).add(v)
                adj.setdefault(v, set()).add(u)
        found: list[dict[str, int]] = []

        def extend(image: dict[str, int]):
            if len(image) == len(steps):
                yield dict(image)
                return
            v = steps[len(image)]
            near = [image[w] for w in p.neighbours[v] if w in image]
            for n in set.intersection(*[adj[x] for x in near]) if near else adj:
                if all(n != m and ((w, v) not in order or m < n) and ((v, w) not in order or n < m) for w, m in image.items()):
                    image[v] = n
                    yield from extend(image)
                    del image[v]

        for match in extend({}):
            found.append(match)
            if len(found) == 10_000:
                yield pa.RecordBatch.from_arrays([pa.array([m[v] for m in found], pa.int64()) for v in p.vertices], names)
                found = []
        yield pa.RecordBatch.from_arrays([pa.array([m[v] for m in found], pa.int64()) for v in p.vertices], names)

    return edges.select("u", "v").coalesce(1).mapInArrow(run, ", ".join(f"{n} bigint" for n in names))


def brute_force_sql(p: Pattern, order: Order, edges: str = "edges", select: str | None = None) -> str:
    """The definition as a self-join of directed edges: a query over a table ``edges(u, v)`` that Spark and DuckDB run."""
    steps = [max(p.vertices, key=p.degree)]
    sources, conditions, at = [], [], {}
    both = f"(SELECT u AS x, v AS y FROM {edges} UNION ALL SELECT v, u FROM {edges})"
    while len(steps) < len(p.vertices):
        v = max((w for w in p.vertices if w not in steps), key=lambda w: len(p.neighbours[w] & set(steps)))
        near, *more = sorted(p.neighbours[v] & set(steps))
        k = len(sources)
        sources.append(f"{both} e{k}")
        if not at:
            at[steps[0]] = f"e{k}.x"
        conditions.append(f"e{k}.x = {at[near]}") if k else None
        at[v] = f"e{k}.y"
        for w in more:
            k = len(sources)
            sources.append(f"{both} e{k}")
            conditions += [f"e{k}.x = {at[w]}", f"e{k}.y = {at[v]}"]
        for w in steps:
            conditions.append(f"{at[w]} < {at[v]}" if (w, v) in order else f"{at[v]} < {at[w]}" if (v, w) in order else f"{at[w]} <> {at[v]}")
        steps.append(v)
    chosen = select or ", ".join(f"{at[v]} AS f_{v}" for v in p.vertices)
    return f"SELECT {chosen} FROM {', '.join(sources)} WHERE {' AND '.join(c for c in conditions if c)}"


def unit_triangles(edges: DataFrame) -> DataFrame:
    """Preprocessing of both rivals for cliques of three."""
    return triangles(edges)
