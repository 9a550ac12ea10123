"""The engine's front: load a graph, plan, list, count, update, stream."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise, materialise_bucketed
from motifmill.operators import compress as K
from motifmill.operators.incremental import drop_removed, patch_set
from motifmill.operators.join import run_tree
from motifmill.operators.store import (
    Partitioner,
    build_store,
    degrees,
    normalize_update,
    partition_bitmaps,
    star_lists,
    update_store,
    updated_edges,
)
from motifmill.plans.estimate import Degrees, Sizes, degree_moments
from motifmill.plans.pattern import PATTERNS, Order, Pattern, named, symmetry_order
from motifmill.plans.planner import PIPELINED, Tree, Weights, best_plan, cost_total, left_deep_plans, optimal_tree


@dataclass(frozen=True)
class Plan:
    """What the engine has decided for a pattern."""

    pattern: Pattern
    order: Order
    cover: frozenset[str] | None
    tree: Tree
    sizes: Sizes

    def text(self, store_ints: float = 0) -> str:
        lines = [f"pattern {self.pattern}", f"order {sorted(self.order)}", f"cover {sorted(self.cover) if self.cover else 'none (plain matches)'}", f"joins {self.tree.joins}"]
        if self.cover:
            parts, orders = left_deep_plans(self.pattern, self.cover)
            lines += [f"least units {[f'{a}: {q}' for a, q in parts]}", f"patch trees {orders}", f"cost {cost_total(self.tree, store_ints, self.sizes, self.cover):.0f}"]
        return "\n".join([*lines, self.tree.text()])


@dataclass
class SubgraphEngine:
    """One data graph, its neighbourhood store and the patterns asked of it.

    ``m`` parts; ``kind`` of the partition function; cost weights of the planner.
    """

    spark: SparkSession
    m: int = 16
    kind: str = "hash"
    weights: Weights = PIPELINED
    method: str = "triangle"
    edges: DataFrame | None = None
    store: DataFrame | None = None
    stats: Degrees | None = None
    matches: dict[str, tuple[Plan, DataFrame]] = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.h = Partitioner(self.m, self.kind)
        # joins on the center and more columns then run on a partitioning by the center alone
        self.spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")

    def load(self, edges: DataFrame) -> SubgraphEngine:
        """Takes canonical edges; writes the graph and its store once."""
        self.edges = materialise(edges, "graph")
        self.store = materialise_bucketed(build_store(self.edges, self.h, self.method), "store", "center")
        self.stats = degree_moments(degrees(self.edges))
        self.matches.clear()
        return self

    def plan(self, pattern: str | Pattern, family: str = "hub", compressed: bool = True, order_factor: str = "auto", bound: str = "tight") -> Plan:
        p = pattern if isinstance(pattern, Pattern) else named(pattern) if pattern in PATTERNS else Pattern.parse(pattern)
        order = symmetry_order(p)
        sizes = Sizes(self.stats, order, order_factor)
        cover, tree = best_plan(p, sizes, family, self.weights, bound) if compressed else (None, optimal_tree(p, sizes, None, family, self.weights))
        return Plan(p, order, cover, tree, sizes)

    def compressed(self, pattern: str | Pattern, materialize: bool = False) -> tuple[Plan, DataFrame]:
        plan = self.plan(pattern)
        return plan, run_tree(self.store, plan.tree, plan.cover, plan.order, materialize)

    def list(self, pattern: str | Pattern, family: str = "hub", compressed: bool = True, limit: int | None = None) -> DataFrame:
        """Plain matches; ``limit`` stops early."""
        plan = self.plan(pattern, family, compressed)
        found = run_tree(self.store, plan.tree, plan.cover, plan.order)
        out = K.decompress(found, plan.pattern, plan.cover, plan.order) if compressed else found
        return out.limit(limit) if limit else out

    def count(self, pattern: str | Pattern) -> int:
        plan, found = self.compressed(pattern)
        return int(K.count_matches(found, plan.pattern, plan.cover, plan.order).first()[0])

    def watch(self, pattern: str | Pattern) -> Plan:
        """Keeps a pattern's compressed matches, so that updates maintain them."""
        plan, found = self.compressed(pattern)
        self.matches[str(plan.pattern)] = (plan, materialise(found, "matches"))
        return plan

    def apply(self, update: DataFrame, route: str = "intersect") -> dict[str, tuple[DataFrame, DataFrame]]:
        """One batch of (op, u, v): updates graph, store and all watched patterns; returns (patch, removed) plain rows of each."""
        deleted, added = (materialise(x, "update") for x in normalize_update(self.edges, update))
        new_edges = materialise(updated_edges(self.edges, deleted, added), "graph")
        new_store = materialise_bucketed(update_store(self.store, star_lists(self.store, deleted, added), deleted, added, self.h), "store", "center")
        bitmaps = partition_bitmaps(new_edges, self.h) if route == "bitmap" else None
        changes = {}
        for name, (plan, old) in self.matches.items():
            p, cover, order = plan.pattern, plan.cover, plan.order
            left = drop_removed(old, p, deleted, cover)
            patch = materialise(patch_set(new_store, p, cover, order, added, self.h, route, bitmaps), "patch")
            now = materialise(left.unionByName(patch), "matches")
            gone = K.decompress(old, p, cover, order).exceptAll(K.decompress(left, p, cover, order))
            changes[name] = (K.decompress(patch, p, cover, order), gone)
            self.matches[name] = (plan, now)
        self.edges, self.store = new_edges, new_store
        self.stats = degree_moments(degrees(new_edges))
        return changes

    def current(self, pattern: str | Pattern) -> DataFrame:
        """Plain matches of a watched pattern."""
        p = pattern if isinstance(pattern, Pattern) else named(pattern) if pattern in PATTERNS else Pattern.parse(pattern)
        plan, found = self.matches[str(p)]
        return K.decompress(found, plan.pattern, plan.cover, plan.order)

    def recompute(self, update: DataFrame, pattern: str | Pattern) -> DataFrame:
        """Matches after an update, from scratch: what maintaining competes with."""
        deleted, added = normalize_update(self.edges, update)
        return SubgraphEngine(self.spark, self.m, self.kind, self.weights).load(updated_edges(self.edges, deleted, added)).list(pattern)

    def explain(self, pattern: str | Pattern) -> str:
        return self.plan(pattern).text()


def participation(matches: DataFrame) -> DataFrame:
    """(v, matches): how many plain matches each data vertex is in."""
    columns = F.array(*[F.col(c) for c in matches.columns])
    return matches.select(F.explode(columns).alias("v")).groupBy("v").agg(F.count("*").alias("matches"))


def top_vertices(matches: DataFrame, k: int) -> DataFrame:
    """The ``k`` vertices in most matches, ties by id."""
    return participation(matches).orderBy(F.desc("matches"), "v").limit(k)


def top_vertices_per_group(matches: DataFrame, groups: DataFrame, k: int) -> DataFrame:
    """The ``k`` vertices in most matches of each group of ``groups(v, g)``."""
    rank = F.row_number().over(Window.partitionBy("g").orderBy(F.desc("matches"), "v"))
    return participation(matches).join(groups, "v").withColumn("rank", rank).where(F.col("rank") <= k)


def register_views(engine: SubgraphEngine, pattern: str, prefix: str = "") -> None:
    """Temporary views ``edges``, ``store`` and ``matches`` for SQL."""
    engine.edges.createOrReplaceTempView(f"{prefix}edges")
    engine.store.createOrReplaceTempView(f"{prefix}store")
    engine.list(pattern).createOrReplaceTempView(f"{prefix}matches")


def subgraphs(spark: SparkSession, view: str, pattern: str, name: str = "subgraphs") -> DataFrame:
    """SQL's way in: lists a pattern in a view (u, v) and registers the matches as a view."""
    from motifmill.sources.graphs import canonical_edges

    out = SubgraphEngine(spark).load(canonical_edges(spark.table(view))).list(pattern)
    out.createOrReplaceTempView(name)
    return out
