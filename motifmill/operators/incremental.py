"""Matches after an update: survivors of the old ones and the patch set of new ones.

A new match has an inserted edge. The units of a pattern are numbered; a match
belongs to the first unit that holds an inserted edge of it. The tree of unit i starts
with matches of unit i that have an inserted edge which no lower unit holds, and goes on
with the other units in an order that always shares a cover vertex; lower units then
may not have inserted edges. So trees are disjoint and need no distinct.

"Some edge of the unit is inserted" is no product of candidate sets, so a seed is cut by
the first own edge that is inserted; for each such slice the conditions on the other
edges are conditions on a skeleton or on one set.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise
from motifmill.operators.compress import decompress, fragments, free, kept
from motifmill.operators.join import compressed_join, union
from motifmill.operators.listing import list_unit_compressed
from motifmill.operators.store import STAR, Partitioner, both_ways, edges_around, parts_of_bitmap
from motifmill.plans.pattern import Edge, Order, Pattern
from motifmill.plans.planner import left_deep_plans


def reach(p: Pattern) -> int:
    """The least number of steps from any edge of the pattern within which every edge has an end."""
    most = 0
    for e in p.edges:
        steps, front = dict.fromkeys(e, 0), list(e)
        for v in front:
            for w in sorted(p.neighbours[v] - steps.keys()):
                steps[w] = steps[v] + 1
                front.append(w)
        most = max(most, *(min(steps[x], steps[y]) for x, y in p.edges))
    return most


def edges_near(edges: DataFrame, p: Pattern, changed: DataFrame) -> DataFrame:
    """All edges of the matches that have an edge of ``changed``, which are edges of the graph, and few others."""
    return edges_around(edges, both_ways(changed), reach(p))


def _ends(x: str, y: str) -> tuple:
    return F.least(F.col(x), F.col(y)), F.greatest(F.col(x), F.col(y))


def _on_edge(rows: DataFrame, x: str, y: str, edges: DataFrame, how: str) -> DataFrame:
    """Rows whose images of x and y are (left_semi) or are not (left_anti) an edge of a list."""
    a, b = _ends(x, y)
    named = edges.select(F.col("u").alias("__u"), F.col("v").alias("__v"))
    return rows.join(named, (a == F.col("__u")) & (b == F.col("__v")), how)


def _lists(edges: DataFrame, name: str) -> DataFrame:
    return both_ways(edges).groupBy("v").agg(F.collect_list("n").alias(name))


def edge_condition(cm: DataFrame, edge: Edge, edges: DataFrame, wanted: bool, cover: frozenset[str]) -> DataFrame:
    """Compressed rows narrowed to matches whose image of a pattern edge is (or is not) in a list of data edges.

    A pattern edge has at most one end outside the cover, so this filters rows or one set.
    """
    x, y = edge
    if x in cover and y in cover:
        return _on_edge(cm, f"s_{x}", f"s_{y}", edges, "left_semi" if wanted else "left_anti")
    x, y = (x, y) if x in cover else (y, x)
    columns = cm.columns
    lists = _lists(edges, "__l").withColumnRenamed("v", "__v")
    met = cm.join(lists, F.col(f"s_{x}") == F.col("__v"), "inner" if wanted else "left")
    other = F.col("__l") if wanted else F.coalesce("__l", F.array().cast("array<bigint>"))
    met = met.withColumn(f"c_{y}", F.array_intersect(f"c_{y}", other) if wanted else F.array_except(f"c_{y}", other))
    return met.where(F.size(f"c_{y}") > 0).select(columns)


def drop_removed(matches: DataFrame, p: Pattern, deleted: DataFrame, cover: frozenset[str] | None = None) -> DataFrame:
    """Matches without a deleted edge, plain (no cover) or compressed."""
    for x, y in p.edges:
        matches = _on_edge(matches, f"f_{x}", f"f_{y}", deleted, "left_anti") if cover is None else edge_condition(matches, (x, y), deleted, False, cover)
    return matches


def removed(matches: DataFrame, p: Pattern, deleted: DataFrame) -> DataFrame:
    """Plain matches with a deleted edge."""
    return matches.exceptAll(drop_removed(matches, p, deleted))


def is_new(matches: DataFrame, p: Pattern, added: DataFrame) -> DataFrame:
    """Plain matches with an inserted edge."""
    rest = matches
    for x, y in p.edges:
        rest = _on_edge(rest, f"f_{x}", f"f_{y}", added, "left_anti")
    return matches.exceptAll(rest)


def seed_slices(store: DataFrame, q: Pattern, cover: frozenset[str], order: Order, added: DataFrame, own: list[Edge], barred: Iterable[Edge], anchor: str) -> list[DataFrame]:
    """Compressed matches of a unit whose first inserted edge among ``own`` is each of them, with no inserted edge among ``barred``.

    Only centers at an inserted edge are listed: ends of one, or centers that have one as an inner row.
    """
    ab = added.select(F.col("u").alias("a"), F.col("v").alias("b"))
    centers = both_ways(added).select(F.col("v").alias("center")).union(store.where(F.col("kind") != STAR).join(ab, ["a", "b"], "left_semi").select("center")).distinct()
    near = store.join(centers, "center", "left_semi").select(store.columns)
    listed = list_unit_compressed(near, q, cover, order, anchor)
    for e in barred:
        listed = edge_condition(listed, e, added, False, cover)
    if len(own) > 1:
        listed = materialise(listed, "listed")  # every slice reads it
    out = []
    for k, e in enumerate(own):
        part = edge_condition(listed, e, added, True, cover)
        for before in own[:k]:
            part = edge_condition(part, before, added, False, cover)
        out.append(part)
    return out


def route(left: DataFrame, keys: list[str], anchor: str, store: DataFrame, how: str, h: Partitioner, bitmaps: DataFrame | None = None) -> DataFrame:
    """(center): where matches of the next unit that fit ``left`` can be anchored.

    ``anchor``: the anchor is a key, so its image is the center. ``bitmap``: parts set in
    the bitmaps of all keys, and in them the centers next to every key. ``intersect``:
    common neighbours of all keys directly.
    """
    if anchor in keys:
        return left.select(F.col(f"s_{anchor}").alias("center")).distinct()
    stars = store.where(F.col("kind") == STAR).select("part", "center", F.col("b").alias("n"))
    wanted = left.select(*[F.col(f"s_{k}").alias(f"k_{k}") for k in keys]).distinct()
    if how == "bitmap":
        both = wanted
        for k in keys:
            both = both.join(bitmaps.select(F.col("v").alias(f"k_{k}"), F.col("words").alias(f"w_{k}")), f"k_{k}")
        words = F.col(f"w_{keys[0]}")
        for k in keys[1:]:
            words = F.zip_with(words, F.col(f"w_{k}"), lambda a, b: a.bitwiseAND(b))
        wanted = both.select(*[f"k_{k}" for k in keys], F.explode(parts_of_bitmap(words, h.m)).alias("part"))
    for i, k in enumerate(keys):
        on = stars.select(*(["part"] if how == "bitmap" else []), "center", F.col("n").alias(f"k_{k}"))
        names = [f"k_{k}"] + (["part"] if how == "bitmap" else []) + (["center"] if i else [])
        wanted = wanted.join(on, names)
    return wanted.select("center").distinct()


def expand(left: DataFrame, piece: Pattern, store: DataFrame, q: Pattern, anchor: str, cover: frozenset[str], order: Order, barred: Iterable[Edge], added: DataFrame, how: str, h: Partitioner, bitmaps: DataFrame | None) -> DataFrame:
    """Left matches extended by a unit: routed to the centers that can serve them, listed there, joined on the shared cover vertices."""
    keys = [v for v in kept(piece, cover) if v in q.vertices]
    centers = route(left, keys, anchor, store, how, h, bitmaps)
    near = store.join(centers, "center", "left_semi").select(store.columns)
    wanted = left.select(*[f"s_{k}" for k in keys]).distinct()
    right = list_unit_compressed(near, q, cover, order, anchor, only=wanted)
    for e in barred:
        right = edge_condition(right, e, added, False, cover)
    return compressed_join(left, right, piece, q, cover, order)


def patch_trees(store: DataFrame, p: Pattern, cover: frozenset[str], order: Order, added: DataFrame, h: Partitioner, how: str = "intersect", bitmaps: DataFrame | None = None, unit_order: bool = True) -> list[DataFrame]:
    """For each unit, the compressed fragments of the patch set that its tree finds in the updated store.

    Without ``unit_order`` every tree finds all new matches with an inserted edge in its unit, and trees overlap.
    """
    parts, orders = left_deep_plans(p, cover)
    out = []
    for i, (anchor, q) in enumerate(parts):
        lower = {e for _, u in parts[:i] for e in u.edges} if unit_order else set()
        own = [e for e in q.edges if e not in lower]
        if not own:
            continue
        tree, piece = None, q
        for part in seed_slices(store, q, cover, order, added, own, sorted(lower & set(q.edges)), anchor):
            tree = part if tree is None else tree.unionByName(part)  # slices are disjoint, so they go on together
        for j in orders[i][1:]:
            nxt_anchor, u = parts[j]
            barred = sorted(u.edges) if unit_order and j < i else []
            tree = expand(materialise(tree, "seeds"), piece, store, u, nxt_anchor, cover, order, barred, added, how, h, bitmaps)
            piece = union(piece, u)
        out.append(tree.select(*[f"s_{v}" for v in kept(p, cover)], *[f"c_{v}" for v in free(p, cover)]))
    return out


def patch_set(
    store: DataFrame, p: Pattern, cover: frozenset[str], order: Order, added: DataFrame, h: Partitioner,
    how: str = "intersect", bitmaps: DataFrame | None = None, parallel: bool = True, dedup: str = "unit_order",
) -> DataFrame:
    """Compressed fragments of all new matches; a skeleton may have several rows.

    ``parallel`` leaves all trees in one plan that shares scans; otherwise each is
    written before the next starts. ``dedup="distinct"`` drops the unit order and removes
    double matches afterwards, by decompressing.
    """
    trees = patch_trees(store, p, cover, order, added, h, how, bitmaps, dedup == "unit_order")
    if not parallel:
        trees = [materialise(t, "patch-tree") for t in trees]
    out = trees[0]
    for t in trees[1:]:
        out = out.unionByName(t)
    if dedup == "distinct":
        return fragments(decompress(out, p, cover, order).distinct(), p, cover)
    return out


def compact(cm: DataFrame, p: Pattern, cover: frozenset[str], order: Order) -> DataFrame:
    """Fewer rows for the same disjoint fragments, by way of plain matches."""
    return fragments(decompress(cm, p, cover, order), p, cover)


@dataclass(frozen=True)
class Dynamic:
    """State of a pattern on a graph: edges, store and compressed matches."""

    edges: DataFrame
    store: DataFrame
    matches: DataFrame


def apply_batch(state: Dynamic, deleted: DataFrame, added: DataFrame, new_store: DataFrame, new_edges: DataFrame, p: Pattern, cover: frozenset[str], order: Order, h: Partitioner, how: str = "intersect", bitmaps: DataFrame | None = None) -> Dynamic:
    """The state after one batch: survivors and patch set."""
    survivors = drop_removed(state.matches, p, deleted, cover)
    return Dynamic(new_edges, new_store, survivors.unionByName(patch_set(new_store, p, cover, order, added, h, how, bitmaps)))
