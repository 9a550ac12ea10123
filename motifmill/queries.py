"""Registered queries of the subgraph engine, and DuckDB SQL for each that SQL can express."""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property, partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.api import participation
from motifmill.functions.scratch import fresh_path, materialise, materialise_bucketed
from motifmill.operators import baselines as B
from motifmill.operators import compress as K
from motifmill.operators import incremental as I
from motifmill.operators import store as S
from motifmill.operators.counting import COUNTS, listed_triangles
from motifmill.operators.join import run_tree
from motifmill.operators.listing import list_unit
from motifmill.plans.estimate import Sizes, degree_moments, expected_matches, relaxed_matches
from motifmill.plans.pattern import named, symmetry_order
from motifmill.plans.planner import best_plan, cost_total, optimal_tree
from motifmill.sources.graphs import GRAPH_SQL, GRAPHS, edges_sql, emb_knn5, update_batch, update_sql

Query = Callable[[SparkSession, str], DataFrame]
PARTS = 16
MOD = S.Partitioner(PARTS, "mod")
BATCH = 100
MAIN = ["square", "triangle", "house", "diamond", "wheel4", "k4tri"]
FURTHER = ["path3", "path4", "star3", "clique4", "clique5", "fan4", "bowtie", "cycle5", "two_triangles_bridge"]


def edges_of(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    return materialise(GRAPHS[graph](spark, sf_dir), f"edges-{graph}", "zstd")


def store_of(edges: DataFrame) -> DataFrame:
    """The store as a table bucketed by center; joins on the center and more columns keep to that."""
    return bucketed(S.build_store(edges, MOD))


def bucketed(store: DataFrame) -> DataFrame:
    store.sparkSession.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")
    return materialise_bucketed(store, "store", "center")


def batch_of(edges: DataFrame, size: int = BATCH) -> tuple[DataFrame, DataFrame]:
    """Effective (deleted, added) of the arithmetic batch, which is drawn once."""
    update = materialise(update_batch(edges, size), "update")
    return tuple(materialise(x, "batch") for x in S.normalize_update(edges, update))


class Setting:
    """A pattern on a graph, planned: pattern, order, cover, tree, edges; the store is written when it is asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str, graph: str, pattern: str, family: str = "hub", compressed: bool = True):
        self.p = named(pattern)
        self.order = symmetry_order(self.p)
        self.edges = edges_of(spark, sf_dir, graph)
        self.sizes = Sizes(degree_moments(S.degrees(self.edges)), self.order)
        if compressed:
            self.cover, self.tree = best_plan(self.p, self.sizes, family)
        else:
            self.cover, self.tree = None, optimal_tree(self.p, self.sizes, None, family)

    @cached_property
    def store(self) -> DataFrame:
        return store_of(self.edges)

    def matches(self, **how) -> DataFrame:
        return run_tree(self.store, self.tree, self.cover, self.order, **how)

    def plain(self, cm: DataFrame) -> DataFrame:
        return K.decompress(cm, self.p, self.cover, self.order)

    def batch(self, size: int = BATCH) -> tuple[DataFrame, DataFrame]:
        return batch_of(self.edges, size)

    def later(self, deleted: DataFrame, added: DataFrame) -> tuple[DataFrame, DataFrame]:
        edges = materialise(S.updated_edges(self.edges, deleted, added), "edges")
        return edges, bucketed(S.update_store(self.store, S.star_lists(self.store, deleted, added), deleted, added, MOD))


# -- graph and store -----------------------------------------------------------


def edges_query(spark, sf_dir, graph):
    return GRAPHS[graph](spark, sf_dir)


def degree_query(spark, sf_dir, graph):
    return S.adjacency(GRAPHS[graph](spark, sf_dir)).select("v", F.col("deg").cast("bigint").alias("deg"), F.array_join("nbrs", ",").alias("nbrs"))


def triangles_query(spark, sf_dir, graph):
    return COUNTS["triangle"](edges_of(spark, sf_dir, graph)).select(F.col("n").cast("bigint").alias("triangles"))


def store_query(spark, sf_dir, graph, method="triangle"):
    rows = S.build_store(edges_of(spark, sf_dir, graph), MOD, method)
    return rows.select(*[F.col(c).cast("bigint").alias(c) for c in ("part", "center", "a", "b", "kind")])


def space_query(spark, sf_dir, graph):
    edges = edges_of(spark, sf_dir, graph)
    both = S.space_actual(store_of(edges), MOD).join(S.space_bound(edges, PARTS))
    return both.select("star", "stored", "extra", "edges", "triangles", "bound")


def merged_query(spark, sf_dir, graph):
    return S.part_sizes(store_of(edges_of(spark, sf_dir, graph))).select(F.col("part").cast("bigint").alias("part"), "edges")


def bitmaps_query(spark, sf_dir, graph):
    h = S.Partitioner(40, "mod")
    return S.partition_bitmaps(edges_of(spark, sf_dir, graph), h).select("v", F.array_join(S.parts_of_bitmap(F.col("words"), h.m), ",").alias("parts"))


def moments_query(spark, sf_dir, graph):
    d = degree_moments(S.degrees(edges_of(spark, sf_dir, graph)), 4)
    rows = [(j + 1, round(d.truncated[j], 4), d.n, d.edges) for j in range(4)]
    return spark.createDataFrame(rows, "j bigint, moment double, n bigint, edges bigint")


def update_store_query(spark, sf_dir, graph):
    """The store after a batch. The one before is a plan over edges and triangles; only what changes in it is written."""
    edges = edges_of(spark, sf_dir, graph)
    deleted, added = batch_of(edges)
    store = S.store_rows(edges, listed_triangles(edges), MOD)
    lists = materialise(S.star_lists(store, deleted, added), "lists")
    delta = S.delta_store(store, lists, deleted, added, MOD)
    store = S.apply_delta(store, S.StoreDelta(materialise(delta.dropped, "dropped"), materialise(delta.inserted, "inserted")))
    return store.select(*[F.col(c).cast("bigint").alias(c) for c in ("part", "center", "a", "b", "kind")])


def update_messages_query(spark, sf_dir, graph):
    edges = edges_of(spark, sf_dir, graph)
    return S.update_messages(S.adjacency(edges), *S.normalize_update(edges, update_batch(edges, BATCH)))


# -- static listing --------------------------------------------------------------


def list_query(spark, sf_dir, graph, pattern, family="hub", compressed=True):
    s = Setting(spark, sf_dir, graph, pattern, family, compressed)
    return s.plain(s.matches()) if compressed else s.matches()


def unit_engine_query(spark, sf_dir, graph, pattern, engine):
    p = named(pattern)
    return list_unit(store_of(edges_of(spark, sf_dir, graph)), p, symmetry_order(p), engine=engine)


def count_query(spark, sf_dir, graph, pattern):
    if pattern in COUNTS:
        return COUNTS[pattern](edges_of(spark, sf_dir, graph)).select(F.col("n").cast("bigint").alias("matches"))
    s = Setting(spark, sf_dir, graph, pattern)
    return K.count_matches(s.matches(), s.p, s.cover, s.order).select(F.col("matches").cast("bigint").alias("matches"))


def compressed_query(spark, sf_dir, graph, pattern, cover="ac", how="intersect"):
    """Compressed matches by a fixed cover, sets rendered."""
    p = named(pattern)
    order, cover = symmetry_order(p), frozenset(cover)
    edges = edges_of(spark, sf_dir, graph)
    tree = optimal_tree(p, Sizes(degree_moments(S.degrees(edges)), order), cover)
    cm = run_tree(store_of(edges), tree, cover, order, how=how)
    cm = K.compress(K.decompress(K.prune(cm, p, cover, order, "exact"), p, cover, order), p, cover) if len(K.free(p, cover)) > 1 else cm
    return cm.select(*[f"s_{v}" for v in K.kept(p, cover)], *[F.array_join(f"c_{v}", ",").alias(f"c_{v}") for v in K.free(p, cover)])


def ratio_query(spark, sf_dir, graph, pattern, cover):
    p = named(pattern)
    order, cover = symmetry_order(p), frozenset(cover)
    edges = edges_of(spark, sf_dir, graph)
    tree = optimal_tree(p, Sizes(degree_moments(S.degrees(edges)), order), cover)
    cm = materialise(run_tree(store_of(edges), tree, cover, order), "matches")
    return K.ratio(cm, p, cover, order).select("matches", "ints", F.round("ratio", 6).alias("ratio"))


def squares_query(spark, sf_dir):
    """Squares of customers and suppliers, from pairs of opposite vertices."""
    return count_query(spark, sf_dir, "cust_supp", "square")


def cliques_query(spark, sf_dir, graph, k):
    rows = B.list_cliques(edges_of(spark, sf_dir, graph), k)
    t = F.sort_array(F.array(*rows.columns))
    return rows.select(*[t[j].alias(f"v{j + 1}") for j in range(k)])


def estimate_query(spark, sf_dir, graph):
    """Estimates with both order factors and the relaxed one beside exact counts."""
    d = degree_moments(S.degrees(edges_of(spark, sf_dir, graph)))
    rows = []
    for name in MAIN:
        p = named(name)
        o = symmetry_order(p)
        truth = count_query(spark, sf_dir, graph, name).first()[0]
        rows.append((name, truth, expected_matches(p, o, d), expected_matches(p, o, d, "linear_extension"), relaxed_matches(p, d)))
    return spark.createDataFrame(rows, "pattern string, truth bigint, auto double, linear_extension double, relaxed double")


def plan_query(spark, sf_dir, graph):
    """Joins, cost and cover that the planner chooses for each pattern."""
    edges = edges_of(spark, sf_dir, graph)
    d, rows = degree_moments(S.degrees(edges)), []
    for name in [*MAIN, *FURTHER]:
        p = named(name)
        sizes = Sizes(d, symmetry_order(p))
        cover, tree = best_plan(p, sizes)
        rows.append((name, "".join(sorted(cover)), tree.joins, cost_total(tree, 4.0 * d.edges, sizes, cover)))
    return spark.createDataFrame(rows, "pattern string, cover string, joins int, cost double")


# -- rivals ------------------------------------------------------------------------


def star_clique_query(spark, sf_dir, graph, pattern):
    p = named(pattern)
    order, edges, rival = symmetry_order(p), edges_of(spark, sf_dir, graph), B.StarCliqueBaseline()
    return rival.list(rival.prepare(edges), p, order, rival.plan(p, Sizes(degree_moments(S.degrees(edges)), order)))


def clique_index_query(spark, sf_dir, graph, pattern):
    p = named(pattern)
    order, edges, rival = symmetry_order(p), edges_of(spark, sf_dir, graph), B.CliqueIndexBaseline()
    cm, core = rival.list(rival.prepare(edges), p, order)
    return K.decompress(cm, p, core, order)


def delta_query(spark, sf_dir, graph, pattern):
    p = named(pattern)
    edges = edges_of(spark, sf_dir, graph)
    deleted, added = (materialise(x, "batch") for x in S.normalize_update(edges, update_batch(edges, BATCH)))
    out = B.DeltaQueryBaseline().update(edges, deleted, added, p, symmetry_order(p))
    return out.withColumn("sign", F.col("sign").cast("bigint"))


def centralised_query(spark, sf_dir, graph, pattern):
    p = named(pattern)
    return B.list_centralised(edges_of(spark, sf_dir, graph), p, symmetry_order(p))


def brute_force_query(spark, sf_dir, graph, pattern):
    p = named(pattern)
    edges_of(spark, sf_dir, graph).createOrReplaceTempView("motifmill_edges")
    return spark.sql(B.brute_force_sql(p, symmetry_order(p), "motifmill_edges"))


# -- dynamic -------------------------------------------------------------------------


def removed_query(spark, sf_dir, graph, pattern):
    """Matches with a deleted edge: what the deleted edges would add to the others. Only the edges around them are stored."""
    s = Setting(spark, sf_dir, graph, pattern)
    deleted, _ = s.batch()
    near = store_of(materialise(I.edges_near(s.edges, s.p, deleted), "near-edges"))
    return s.plain(I.patch_set(near, s.p, s.cover, s.order, deleted, MOD))


def patch_query(spark, sf_dir, graph, pattern, how="intersect", dedup="unit_order", parallel=True):
    s = Setting(spark, sf_dir, graph, pattern)
    deleted, added = s.batch()
    edges, store = s.later(deleted, added)
    bitmaps = materialise(S.partition_bitmaps(edges, MOD), "bitmaps") if how == "bitmap" else None
    return s.plain(I.patch_set(store, s.p, s.cover, s.order, added, MOD, how, bitmaps, parallel, dedup))


def updated_query(spark, sf_dir, graph, pattern):
    """Matches after the batch: survivors and patch.

    A triangle's survivors come from triangles listed in slices, and its patch from the edges around the inserted ones, so
    no store of the whole graph is written.
    """
    s = Setting(spark, sf_dir, graph, pattern)
    deleted, added = s.batch()
    if pattern == "triangle":
        near = S.updated_edges(I.edges_near(s.edges, s.p, added), deleted, added)
        patch = s.plain(I.patch_set(store_of(materialise(near, "near-edges")), s.p, s.cover, s.order, added, MOD))
        ranked = sorted(s.p.vertices, key=lambda v: sum(y == v for _, y in s.order))  # a triangle's order is total
        old = listed_triangles(s.edges).select(*[F.col(c).alias(f"f_{v}") for c, v in zip("xyz", ranked, strict=True)])
        return I.drop_removed(old, s.p, deleted).select(patch.columns).union(patch)
    edges, store = s.later(deleted, added)
    old = I.Dynamic(s.edges, s.store, materialise(s.matches(), "matches"))
    return s.plain(I.apply_batch(old, deleted, added, store, edges, s.p, s.cover, s.order, MOD).matches)


def recompute_query(spark, sf_dir, graph, pattern):
    """The same from scratch on the new graph."""
    s = Setting(spark, sf_dir, graph, pattern)
    edges = S.updated_edges(s.edges, *s.batch())
    return s.plain(run_tree(store_of(materialise(edges, "edges")), s.tree, s.cover, s.order))


def bushy_query(spark, sf_dir, graph, pattern):
    s = Setting(spark, sf_dir, graph, pattern)
    deleted, added = s.batch()
    _, store = s.later(deleted, added)
    return B.patch_bushy(store, s.matches(), s.p, s.order, s.tree, added, s.cover)


def stream_query(spark, sf_dir, graph="events_3d", pattern="triangle"):
    """Matches after a file stream of three updates, through ``foreachBatch``."""
    from motifmill.streaming.replay import Maintainer, read_updates

    s = Setting(spark, sf_dir, graph, pattern)
    keeper = Maintainer(spark, fresh_path(spark, "stream-state"), s.p, s.cover, s.order, MOD)
    keeper.start(s.edges, s.matches())
    folder = fresh_path(spark, "stream-input")
    batch = update_batch(s.edges, BATCH)
    third = F.pmod(F.col("u") + F.col("v"), F.lit(3))
    for k in range(3):
        batch.where(third == k).select(F.col("batch_id").cast("bigint").alias("batch_id"), "op", "u", "v").coalesce(1).write.mode("append").parquet(folder)
    keeper.run(read_updates(spark, folder), fresh_path(spark, "stream-checkpoint"))
    return keeper.current()


# -- reports ------------------------------------------------------------------------


def topk_query(spark, sf_dir, graph, pattern, k=10):
    s = Setting(spark, sf_dir, graph, pattern)
    return participation(s.plain(s.matches())).orderBy(F.desc("matches"), "v").limit(k)


def rollup_query(spark, sf_dir):
    """Squares of customers and suppliers by region and nation of the first customer, with totals: supplier pairs that two customers share."""
    edges = edges_of(spark, sf_dir, "cust_supp")
    pairs = S.both_ways(edges).where(F.col("v") % 2 == 0).select((F.col("v") / 2).cast("bigint").alias("c_custkey"))
    customer, nation, region = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("customer", "nation", "region"))
    named_ = pairs.join(customer.select("c_custkey", "c_nationkey"), "c_custkey")
    named_ = named_.join(F.broadcast(nation.select("n_nationkey", "n_name", "n_regionkey")), F.col("c_nationkey") == F.col("n_nationkey"))
    named_ = named_.join(F.broadcast(region.select("r_regionkey", "r_name")), F.col("n_regionkey") == F.col("r_regionkey"))
    return named_.rollup("r_name", "n_name").agg(F.count("*").alias("edges"), F.grouping_id().cast("bigint").alias("level"))


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {}
    for g in GRAPH_SQL:
        out[f"edges_{g}"] = partial(edges_query, graph=g)
        out[f"degree_{g}"] = partial(degree_query, graph=g)
    out["edges_emb_knn5"] = emb_knn5
    for g in ("events_3d", "events_seq", "doc_lines", "copart_ge2", "copart", "fk_graph", "cust_supp"):
        out[f"triangles_{g}"] = partial(triangles_query, graph=g)
    for g in ("events_3d", "copart_ge2", "doc_lines"):
        out[f"store_rows_{g}"] = partial(store_query, graph=g)
        out[f"store_space_{g}"] = partial(space_query, graph=g)
        out[f"moments_{g}"] = partial(moments_query, graph=g)
        out[f"bitmaps_{g}"] = partial(bitmaps_query, graph=g)
    out["store_rows_ship_events_3d"] = partial(store_query, graph="events_3d", method="ship")
    out["store_parts_events_3d"] = partial(merged_query, graph="events_3d")
    out["update_store_events_3d"] = partial(update_store_query, graph="events_3d")
    out["update_store_copart_ge2"] = partial(update_store_query, graph="copart_ge2")
    out["update_messages_events_3d"] = partial(update_messages_query, graph="events_3d")
    for p in [*MAIN, *FURTHER]:
        out[f"list_{p}_events_3d"] = partial(list_query, graph="events_3d", pattern=p)
    for p in MAIN:
        out[f"list_{p}_copart_ge2"] = partial(list_query, graph="copart_ge2", pattern=p)
    for p in ("triangle", "square", "diamond"):
        out[f"count_{p}_doc_lines"] = partial(count_query, graph="doc_lines", pattern=p)
    out["count_triangle_fk_graph"] = partial(count_query, graph="fk_graph", pattern="triangle")
    out["count_triangle_copart"] = partial(count_query, graph="copart", pattern="triangle")
    out["count_square_cust_supp"] = squares_query
    out["count_triangle_events_seq"] = partial(count_query, graph="events_seq", pattern="triangle")
    out["list_cycle6_events_3d"] = partial(list_query, graph="events_3d", pattern="cycle6")
    out["list_triangle_fk_graph"] = partial(list_query, graph="fk_graph", pattern="triangle")
    out["patch_triangle_fk_graph"] = partial(patch_query, graph="fk_graph", pattern="triangle")
    out["updated_triangle_fk_graph"] = partial(updated_query, graph="fk_graph", pattern="triangle")
    out["removed_triangle_fk_graph"] = partial(removed_query, graph="fk_graph", pattern="triangle")
    out["update_store_fk_graph"] = partial(update_store_query, graph="fk_graph")
    out["compressed_square"] = partial(compressed_query, graph="events_3d", pattern="square", cover="abc")
    out["compressed_triangle"] = partial(compressed_query, graph="events_3d", pattern="triangle", cover="ab")
    out["compressed_triangle_grouped"] = partial(compressed_query, graph="events_3d", pattern="triangle", cover="ab", how="group")
    out["compressed_diamond"] = partial(compressed_query, graph="events_3d", pattern="diamond", cover="ac")
    out["compression_ratio_square"] = partial(ratio_query, graph="events_3d", pattern="square", cover="abc")
    out["compression_ratio_wheel4"] = partial(ratio_query, graph="events_3d", pattern="wheel4", cover="habc")
    for e in ("relational", "arrow_dfs", "hof"):
        out[f"unit_engine_{e}_triangle"] = partial(unit_engine_query, graph="events_3d", pattern="triangle", engine=e)
    out["cliques4_events_3d"] = partial(cliques_query, graph="events_3d", k=4)
    for p in ("square", "diamond", "k4tri"):
        out[f"baseline_star_clique_{p}"] = partial(star_clique_query, graph="events_3d", pattern=p)
        out[f"baseline_clique_index_{p}"] = partial(clique_index_query, graph="events_3d", pattern=p)
    out["baseline_triangle_family_k4tri"] = partial(list_query, graph="events_3d", pattern="k4tri", family="triangles")
    out["baseline_clique_family_k4tri"] = partial(list_query, graph="events_3d", pattern="k4tri", family="cliques")
    out["baseline_uncompressed_square"] = partial(list_query, graph="events_3d", pattern="square", compressed=False)
    out["baseline_centralised_diamond"] = partial(centralised_query, graph="events_3d", pattern="diamond")
    out["baseline_brute_force_square"] = partial(brute_force_query, graph="events_3d", pattern="square")
    for p in ("triangle", "square", "diamond"):
        out[f"baseline_delta_query_{p}"] = partial(delta_query, graph="events_3d", pattern=p)
    for p in ("triangle", "square", "diamond", "house", "wheel4"):
        out[f"removed_{p}"] = partial(removed_query, graph="events_3d", pattern=p)
        out[f"patch_{p}"] = partial(patch_query, graph="events_3d", pattern=p)
        out[f"updated_{p}"] = partial(updated_query, graph="events_3d", pattern=p)
    out["patch_bitmap_square"] = partial(patch_query, graph="events_3d", pattern="square", how="bitmap")
    out["patch_bridge_anchor_route"] = partial(patch_query, graph="events_3d", pattern="two_triangles_bridge")
    out["patch_distinct_square"] = partial(patch_query, graph="events_3d", pattern="square", dedup="distinct")
    out["patch_serial_square"] = partial(patch_query, graph="events_3d", pattern="square", parallel=False)
    out["baseline_recompute_square"] = partial(recompute_query, graph="events_3d", pattern="square")
    out["baseline_bushy_patch_square"] = partial(bushy_query, graph="events_3d", pattern="square")
    out["stream_replay"] = stream_query
    out["participation_topk"] = partial(topk_query, graph="events_3d", pattern="house")
    out["edges_by_region_rollup"] = rollup_query
    out["estimate_events_3d"] = partial(estimate_query, graph="events_3d")
    out["plan_choices_events_3d"] = partial(plan_query, graph="events_3d")
    return out


# -- SQL ------------------------------------------------------------------------------


def _listing(graph: str, pattern: str) -> str:
    p = named(pattern)
    return f"WITH {edges_sql(graph)} {B.brute_force_sql(p, symmetry_order(p))}"


def _both(edges: str = "edges") -> str:
    return f"(SELECT u AS x, v AS y FROM {edges} UNION ALL SELECT v, u FROM {edges})"


def _store_rows(edges: str = "edges") -> str:
    both = _both(edges)
    return f"""SELECT x % {PARTS} AS part, x AS center, x AS a, y AS b, 0::BIGINT AS kind FROM {both}
UNION ALL SELECT s.x % {PARTS}, s.x, e.u, e.v, 1::BIGINT FROM {edges} e JOIN {both} s ON s.y = e.u JOIN {both} t ON t.x = s.x AND t.y = e.v"""


def _compressed(graph: str, pattern: str, cover: str) -> str:
    p = named(pattern)
    kept, free = K.kept(p, frozenset(cover)), K.free(p, frozenset(cover))
    sets = ", ".join(f"array_to_string(list_sort(list_distinct(list(f_{v}))), ',') AS c_{v}" for v in free)
    keys = ", ".join(f"f_{v} AS s_{v}" for v in kept)
    return f"WITH {edges_sql(graph)}, m AS ({B.brute_force_sql(p, symmetry_order(p))}) SELECT {keys}, {sets} FROM m GROUP BY {', '.join(f'f_{v}' for v in kept)}"


def _ratio(graph: str, pattern: str, cover: str) -> str:
    p = named(pattern)
    kept, free = K.kept(p, frozenset(cover)), K.free(p, frozenset(cover))
    sets = " + ".join([*(f"count(DISTINCT f_{v})" for v in free), str(len(kept))])
    return f"""WITH {edges_sql(graph)}, m AS ({B.brute_force_sql(p, symmetry_order(p))}),
g AS (SELECT count(*) AS n, {sets} AS held FROM m GROUP BY {', '.join(f'f_{v}' for v in kept)})
SELECT coalesce(sum(n), 0)::BIGINT AS matches, coalesce(sum(held), 0)::BIGINT AS ints, round(sum(n) * {len(p.vertices)}.0 / sum(held), 6)::DOUBLE AS ratio FROM g"""


def _dynamic(graph: str, pattern: str, what: str) -> str:
    p = named(pattern)
    o = symmetry_order(p)
    old, new = B.brute_force_sql(p, o), B.brute_force_sql(p, o, "later")
    body = {"updated": new, "patch": f"({new}) EXCEPT ({old})", "removed": f"({old}) EXCEPT ({new})"}.get(what)
    if what == "delta":
        body = f"SELECT 1::BIGINT AS sign, * FROM (({new}) EXCEPT ({old})) UNION ALL SELECT -1::BIGINT, * FROM (({old}) EXCEPT ({new}))"
    return f"WITH {edges_sql(graph)}, {update_sql(BATCH)} {body}"


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for g in GRAPH_SQL:
        out[f"edges_{g}"] = f"WITH {edges_sql(g)} SELECT u, v FROM edges"
        out[f"degree_{g}"] = f"WITH {edges_sql(g)} SELECT x AS v, count(*)::BIGINT AS deg, string_agg(y::VARCHAR, ',' ORDER BY y) AS nbrs FROM {_both()} GROUP BY x"
        out[f"triangles_{g}"] = f"WITH {edges_sql(g)} SELECT count(*)::BIGINT AS triangles FROM edges a JOIN edges b ON a.v = b.u JOIN edges c ON c.u = a.u AND c.v = b.v"
    for g in ("events_3d", "copart_ge2", "doc_lines"):
        out[f"store_rows_{g}"] = f"WITH {edges_sql(g)} {_store_rows()}"
        out[f"store_space_{g}"] = f"""WITH {edges_sql(g)}, rows_ AS ({_store_rows()}),
n AS (SELECT count(*) AS edges FROM edges), t AS (SELECT count(*) // 3 AS triangles FROM rows_ WHERE kind = 1),
star AS (SELECT sum(CASE WHEN u % {PARTS} = v % {PARTS} THEN 1 ELSE 2 END) AS star FROM edges),
st AS (SELECT count(*) AS stored FROM (SELECT DISTINCT part, least(a, b), greatest(a, b) FROM rows_))
SELECT star::BIGINT AS star, stored::BIGINT AS stored, (stored - star)::BIGINT AS extra, edges::BIGINT AS edges, triangles::BIGINT AS triangles,
       least(3 * triangles, {PARTS - 1} * edges)::BIGINT AS bound FROM n, t, star, st"""
        out[f"moments_{g}"] = f"""WITH {edges_sql(g)}, d AS (SELECT x, count(*) AS deg FROM {_both()} GROUP BY x)
SELECT j, round(sum(CASE WHEN deg >= j THEN deg::DOUBLE ** j ELSE 0 END) / count(*), 4) AS moment, count(*)::BIGINT AS n, (SELECT count(*) FROM edges)::BIGINT AS edges
FROM d, range(1, 5) r(j) GROUP BY j"""
        out[f"bitmaps_{g}"] = f"WITH {edges_sql(g)} SELECT x AS v, string_agg(p::VARCHAR, ',' ORDER BY p) AS parts FROM (SELECT DISTINCT x, y % 40 AS p FROM {_both()}) GROUP BY x"
    out["store_rows_ship_events_3d"] = out["store_rows_events_3d"]
    out["store_parts_events_3d"] = f"WITH {edges_sql('events_3d')}, r AS ({_store_rows()}) SELECT part, count(*)::BIGINT AS edges FROM (SELECT DISTINCT part, least(a, b), greatest(a, b) FROM r) GROUP BY part"
    for g in ("events_3d", "copart_ge2"):
        out[f"update_store_{g}"] = f"WITH {edges_sql(g)}, {update_sql(BATCH)} {_store_rows('later')}"
    out["update_messages_events_3d"] = f"""WITH {edges_sql('events_3d')}, {update_sql(BATCH)},
touched AS (SELECT u AS x FROM gone UNION SELECT v FROM gone UNION SELECT u FROM come UNION SELECT v FROM come),
d AS (SELECT t.x, count(y) AS deg FROM touched t LEFT JOIN {_both('later')} b ON b.x = t.x GROUP BY t.x)
SELECT count(*)::BIGINT AS vertices, sum(deg)::BIGINT AS shipped, (3 * sum(deg))::BIGINT AS bound FROM d"""
    for p in [*MAIN, *FURTHER]:
        out[f"list_{p}_events_3d"] = _listing("events_3d", p)
    for p in MAIN:
        out[f"list_{p}_copart_ge2"] = _listing("copart_ge2", p)
    for g, p in (("doc_lines", "triangle"), ("doc_lines", "square"), ("doc_lines", "diamond"), ("fk_graph", "triangle"), ("copart", "triangle")):
        q = named(p)
        out[f"count_{p}_{g}"] = f"WITH {edges_sql(g)} {B.brute_force_sql(q, symmetry_order(q), select='count(*)::BIGINT AS matches')}"
    out["count_square_cust_supp"] = f"""WITH {edges_sql('cust_supp')}, e AS (SELECT CASE WHEN u % 2 = 0 THEN u ELSE v END AS c, CASE WHEN u % 2 = 0 THEN v ELSE u END AS s FROM edges),
n AS (SELECT count(*) AS n FROM e a JOIN e b ON a.s = b.s AND a.c < b.c GROUP BY a.c, b.c) SELECT coalesce(sum(n * (n - 1) // 2), 0)::BIGINT AS matches FROM n"""
    out["count_triangle_events_seq"] = f"WITH {edges_sql('events_seq')} {B.brute_force_sql(named('triangle'), symmetry_order(named('triangle')), select='count(*)::BIGINT AS matches')}"
    out["list_cycle6_events_3d"] = _listing("events_3d", "cycle6")
    out["list_triangle_fk_graph"] = _listing("fk_graph", "triangle")
    for what in ("patch", "updated", "removed"):
        out[f"{what}_triangle_fk_graph"] = _dynamic("fk_graph", "triangle", what)
    out["update_store_fk_graph"] = f"WITH {edges_sql('fk_graph')}, {update_sql(BATCH)} {_store_rows('later')}"
    out["compressed_square"] = _compressed("events_3d", "square", "abc")
    out["compressed_triangle"] = out["compressed_triangle_grouped"] = _compressed("events_3d", "triangle", "ab")
    out["compressed_diamond"] = _compressed("events_3d", "diamond", "ac")
    out["compression_ratio_square"] = _ratio("events_3d", "square", "abc")
    out["compression_ratio_wheel4"] = _ratio("events_3d", "wheel4", "habc")
    for e in ("relational", "arrow_dfs", "hof"):
        out[f"unit_engine_{e}_triangle"] = _listing("events_3d", "triangle")
    c4 = named("clique4")
    out["cliques4_events_3d"] = f"WITH {edges_sql('events_3d')}, m AS ({B.brute_force_sql(c4, symmetry_order(c4))}) SELECT f_a AS v1, f_b AS v2, f_c AS v3, f_d AS v4 FROM m"
    for p in ("square", "diamond", "k4tri"):
        out[f"baseline_star_clique_{p}"] = out[f"baseline_clique_index_{p}"] = _listing("events_3d", p)
    out["baseline_triangle_family_k4tri"] = out["baseline_clique_family_k4tri"] = _listing("events_3d", "k4tri")
    out["baseline_uncompressed_square"] = out["baseline_brute_force_square"] = _listing("events_3d", "square")
    out["baseline_centralised_diamond"] = _listing("events_3d", "diamond")
    for p in ("triangle", "square", "diamond"):
        out[f"baseline_delta_query_{p}"] = _dynamic("events_3d", p, "delta")
    for p in ("triangle", "square", "diamond", "house", "wheel4"):
        for what in ("removed", "patch", "updated"):
            out[f"{what}_{p}"] = _dynamic("events_3d", p, what)
    out["patch_bitmap_square"] = out["patch_distinct_square"] = out["patch_serial_square"] = out["baseline_bushy_patch_square"] = _dynamic("events_3d", "square", "patch")
    out["patch_bridge_anchor_route"] = _dynamic("events_3d", "two_triangles_bridge", "patch")
    out["baseline_recompute_square"] = _dynamic("events_3d", "square", "updated")
    out["stream_replay"] = _dynamic("events_3d", "triangle", "updated")
    h = named("house")
    out["participation_topk"] = f"""WITH {edges_sql('events_3d')}, m AS ({B.brute_force_sql(h, symmetry_order(h))})
SELECT v, count(*)::BIGINT AS matches FROM (SELECT unnest([f_a, f_b, f_c, f_d, f_e]) AS v FROM m) GROUP BY v ORDER BY matches DESC, v LIMIT 10"""
    out["edges_by_region_rollup"] = f"""WITH {edges_sql('cust_supp')}
SELECT r_name, n_name, count(*)::BIGINT AS edges, grouping(r_name, n_name)::BIGINT AS level
FROM {_both()} e JOIN customer ON c_custkey = x // 2 AND x % 2 = 0 JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
GROUP BY ROLLUP (r_name, n_name)"""
    return out


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All houses among users of consecutive events."""
    return list_query(spark, sf_dir, "events_3d", "house")
