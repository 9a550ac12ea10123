"""Joins of match sets along a tree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise
from motifmill.operators.compress import all_of, clean_sets, free, kept, pair_condition, prune
from motifmill.operators.listing import list_unit, list_unit_compressed
from motifmill.plans.pattern import Order, Pattern, restrict
from motifmill.plans.planner import Tree


def union(p1: Pattern, p2: Pattern) -> Pattern:
    return Pattern(tuple(sorted({*p1.edges, *p2.edges})))


def plain_join(m1: DataFrame, m2: DataFrame, p1: Pattern, p2: Pattern, order: Order, allow_cross: bool = False) -> DataFrame:
    """Plain matches of the union of two pieces: equal on shared vertices, distinct and in order on the rest."""
    shared = [v for v in p1.vertices if v in p2.vertices]
    if not shared and not allow_cross:
        raise ValueError("the pieces share no vertex")
    out = m1.join(m2, [f"f_{v}" for v in shared]) if shared else m1.crossJoin(m2)
    mine, theirs = [v for v in p1.vertices if v not in shared], [v for v in p2.vertices if v not in shared]
    checks = [pair_condition(x, y, F.col(f"f_{x}"), F.col(f"f_{y}"), order) for x in mine for y in theirs]
    return out.where(all_of(checks)).select(*[f"f_{v}" for v in union(p1, p2).vertices])


def compressed_join(c1: DataFrame, c2: DataFrame, p1: Pattern, p2: Pattern, cover: frozenset[str], order: Order, level: str = "skeleton", allow_cross: bool = False) -> DataFrame:
    """Compressed matches of the union: keys are the shared cover vertices; a free vertex of both sides keeps the
    candidates that both sides have, and loses what the other side's skeleton or the order excludes."""
    p = union(p1, p2)
    keys = [f"s_{v}" for v in kept(p1, cover) if v in p2.vertices]
    if not keys and not allow_cross:
        raise ValueError("the pieces share no cover vertex")
    both = [v for v in free(p1, cover) if v in p2.vertices]
    right = c2
    for v in both:
        right = right.withColumnRenamed(f"c_{v}", f"r_{v}")
    out = c1.join(right, keys) if keys else c1.crossJoin(right)
    mine = [v for v in kept(p1, cover) if v not in p2.vertices]
    theirs = [v for v in kept(p2, cover) if v not in p1.vertices]
    out = out.where(all_of([pair_condition(x, y, F.col(f"s_{x}"), F.col(f"s_{y}"), order) for x in mine for y in theirs]))
    for v in both:
        out = out.withColumn(f"c_{v}", F.array_intersect(f"c_{v}", f"r_{v}"))
    out = out.select(*[f"s_{v}" for v in kept(p, cover)], *[f"c_{v}" for v in free(p, cover)])
    order = restrict(order, p.vertices)
    return clean_sets(out, p, cover, order) if level == "skeleton" else prune(out, p, cover, order, level)


def run_tree(store: DataFrame, tree: Tree, cover: frozenset[str] | None, order: Order, materialize: bool = False, how: str = "intersect") -> DataFrame:
    """Matches at the root of a tree; compressed under a cover, plain without one. A node is written only if asked for."""
    if tree.left is None:
        out = list_unit(store, tree.piece, order) if cover is None else list_unit_compressed(store, tree.piece, cover, order, how=how)
    else:
        left, right = (run_tree(store, t, cover, order, materialize, how) for t in (tree.left, tree.right))
        if cover is None:
            out = plain_join(left, right, tree.left.piece, tree.right.piece, order)
        else:
            out = compressed_join(left, right, tree.left.piece, tree.right.piece, cover, order)
    return materialise(out, "tree-node") if materialize else out
