"""The experiments, on the given tables: ``python -m motifmill.workloads [sf_dir] [W1 ...]`` prints one JSON line a measurement."""

from __future__ import annotations

import json
import sys
import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.functions.metrics import measure
from motifmill.functions.scratch import materialise
from motifmill.operators import baselines as B
from motifmill.operators import compress as K
from motifmill.operators import incremental as I
from motifmill.operators import store as S
from motifmill.operators.join import run_tree
from motifmill.plans.estimate import Sizes, degree_moments, expected_matches, q_error, relaxed_matches
from motifmill.plans.pattern import named, symmetry_order
from motifmill.plans.planner import best_cover, optimal_tree
from motifmill.queries import MAIN, MOD, PARTS
from motifmill.sources.graphs import GRAPHS, event_batches, events_3d, update_batch
from motifmill.sources.sinks import run_only

Row = dict[str, object]
STANDARD = ["square", "triangle", "house", "diamond", "wheel4"]
DATA_GRAPHS = ["events_3d", "copart_ge2", "doc_lines", "events_seq"]


def timed(work: Callable[[], object]) -> tuple[float, object]:
    start = time.perf_counter()
    out = work()
    return round(time.perf_counter() - start, 3), out


def planned(edges: DataFrame, pattern: str, compressed: bool = True, family: str = "hub"):
    p = named(pattern)
    sizes = Sizes(degree_moments(S.degrees(edges)), symmetry_order(p))
    cover = best_cover(p, sizes) if compressed else None
    return p, sizes.order, sizes, cover, optimal_tree(p, sizes, cover, family)


def w1_preprocessing(edges: DataFrame, graph: str) -> Iterator[Row]:
    """Seconds to build the store, by both routes, and the rivals' clique index."""
    for name, work in (
        ("store", lambda: run_only(S.build_store(edges, MOD))),
        ("store_ship", lambda: run_only(S.build_store(edges, MOD, "ship"))),
        ("clique_index", lambda: [run_only(x) for x in B.clique_index(edges, 3).values()]),
    ):
        yield {"workload": "W1", "graph": graph, "method": name, "seconds": timed(work)[0]}


def w2_space(edges: DataFrame, graph: str) -> Iterator[Row]:
    """Integers of the store for several numbers of parts, its bound, and of the rivals' indexes, as ratios to the raw graph."""
    raw = 2 * edges.count()
    for m in (4, 16, 200):
        h = S.Partitioner(m)
        found, bound = S.space_actual(S.build_store(edges, h), h).first(), S.space_bound(edges, m).first()
        yield {"workload": "W2", "graph": graph, "m": m, "ratio": round(2 * found.stored / raw, 3), "extra": found.extra, "bound": bound.bound}
    yield {"workload": "W2", "graph": graph, "method": "clique_index", "ratio": round(B.index_ints(B.clique_index(edges, 3)) / raw, 3)}


def w3_static(edges: DataFrame, graph: str, patterns: list[str] | None = None) -> Iterator[Row]:
    """Seconds, matches and exchanged bytes of three methods; all matches are computed and written to a sink."""
    store = materialise(S.build_store(edges, MOD), "store")
    stars, cliques = B.StarCliqueBaseline(), B.CliqueIndexBaseline()
    index = {k: materialise(x, "index") for k, x in stars.prepare(edges).items()}
    for pattern in patterns or STANDARD:
        p, order, sizes, cover, tree = planned(edges, pattern)
        for method, plan in (
            ("ours", lambda: run_tree(store, tree, cover, order)),
            ("star_clique", lambda: stars.list(index, p, order, stars.plan(p, sizes))),
            ("clique_index", lambda: cliques.list(index, p, order)[0]),
        ):
            spent = measure(edges.sparkSession, lambda plan=plan: run_only(plan()))
            yield {"workload": "W3", "graph": graph, "pattern": pattern, "method": method, "seconds": spent["seconds"], "shuffle_bytes": spent["shuffleWriteBytes"], "joins": tree.joins if method == "ours" else None}


def w4_store_update(edges: DataFrame, graph: str) -> Iterator[Row]:
    """Seconds and shipped integers of store updates against building anew."""
    store, adj, n = materialise(S.build_store(edges, MOD), "store"), materialise(S.adjacency(edges), "adj"), edges.count()
    yield {"workload": "W4", "graph": graph, "b": "build", "seconds": timed(lambda: run_only(S.build_store(edges, MOD)))[0]}
    for b in (100, 1000, 10_000, 100_000):
        if b <= n:
            deleted, added = (materialise(x, "batch") for x in S.normalize_update(edges, update_batch(edges, b)))
            seconds, _ = timed(lambda: run_only(S.update_store(store, adj, deleted, added, MOD)))
            yield {"workload": "W4", "graph": graph, "b": b, "seconds": seconds, "shipped": S.update_messages(adj, deleted, added).first().shipped}


def w5_match_update(edges: DataFrame, graph: str) -> Iterator[Row]:
    """Seconds of match updates, with the store's, against delta queries and recomputing, by batch size."""
    store, adj, n = materialise(S.build_store(edges, MOD), "store"), materialise(S.adjacency(edges), "adj"), edges.count()
    for pattern in STANDARD[:4]:
        p, order, _, cover, tree = planned(edges, pattern)
        cm = materialise(run_tree(store, tree, cover, order), "matches")
        for b in (100, 1000, 10_000):
            if b > n:
                continue
            deleted, added = (materialise(x, "batch") for x in S.normalize_update(edges, update_batch(edges, b)))

            def ours():
                new = materialise(S.update_store(store, adj, deleted, added, MOD), "store")
                run_only(I.drop_removed(cm, p, deleted, cover).unionByName(I.patch_set(new, p, cover, order, added, MOD)))

            for method, work in (
                ("patch", ours),
                ("delta_query", lambda: run_only(B.DeltaQueryBaseline().update(edges, deleted, added, p, order))),
                ("recompute", lambda: run_only(run_tree(S.build_store(S.updated_edges(edges, deleted, added), MOD), tree, cover, order))),
            ):
                yield {"workload": "W5", "graph": graph, "pattern": pattern, "b": b, "method": method, "seconds": timed(work)[0]}


def w6_ablations(edges: DataFrame, graph: str) -> Iterator[Row]:
    """Switches: unit families, compression, listing of units, routing, duplicate rule, serial trees."""
    store = materialise(S.build_store(edges, MOD), "store")
    for family in ("hub", "cliques", "triangles"):
        p, order, _, cover, tree = planned(edges, "k4tri", False, family)
        yield {"workload": "W6", "graph": graph, "switch": f"family={family}", "joins": tree.joins, "seconds": timed(lambda: run_only(run_tree(store, tree, None, order)))[0]}
    for pattern in ("square", "house"):
        for compressed in (True, False):
            p, order, _, cover, tree = planned(edges, pattern, compressed)
            out = run_tree(store, tree, cover, order)
            yield {"workload": "W6", "graph": graph, "pattern": pattern, "switch": f"compressed={compressed}", "seconds": timed(lambda: run_only(out))[0]}
        p, order, _, cover, tree = planned(edges, pattern)
        for how in ("intersect", "group"):
            yield {"workload": "W6", "graph": graph, "pattern": pattern, "switch": f"listing={how}", "seconds": timed(lambda how=how: run_only(run_tree(store, tree, cover, order, how=how)))[0]}
        deleted, added = (materialise(x, "batch") for x in S.normalize_update(edges, update_batch(edges, 100)))
        later = materialise(S.updated_edges(edges, deleted, added), "edges")
        new, bits = materialise(S.build_store(later, MOD), "store"), materialise(S.partition_bitmaps(later, MOD), "bits")
        for switch in ({"how": "bitmap"}, {"how": "intersect"}, {"dedup": "distinct"}, {"parallel": False}):
            seconds, _ = timed(lambda s=switch: run_only(I.patch_set(new, p, cover, order, added, MOD, bitmaps=bits, **s)))
            yield {"workload": "W6", "graph": graph, "pattern": pattern, "switch": str(switch), "seconds": seconds}


def w7_estimates(edges: DataFrame, graph: str) -> Iterator[Row]:
    """q-errors of the estimates with both order factors, and of the relaxed one."""
    d = degree_moments(S.degrees(edges))
    store = materialise(S.build_store(edges, MOD), "store")
    for pattern in MAIN:
        p, order, _, cover, tree = planned(edges, pattern)
        truth = int(K.count_matches(run_tree(store, tree, cover, order), p, cover, order).first()[0])
        yield {
            "workload": "W7", "graph": graph, "pattern": pattern, "truth": truth, "auto": round(q_error(expected_matches(p, order, d), truth), 3),
            "linear_extension": round(q_error(expected_matches(p, order, d, "linear_extension"), truth), 3), "relaxed": round(q_error(relaxed_matches(p, d), truth), 3),
        }


def w8_stream(spark: SparkSession, sf_dir: str, days: int = 3) -> Iterator[Row]:
    """Seconds of each day's batch of first-seen edges, triangles maintained."""
    from motifmill.api import SubgraphEngine

    engine = SubgraphEngine(spark, PARTS).load(events_3d(spark, sf_dir))
    engine.watch("triangle")
    batches = materialise(event_batches(spark, sf_dir, days=days), "batches")
    for day in range(days):
        update = batches.where(F.col("batch_id") == day)
        seconds, _ = timed(lambda u=update: engine.apply(u))
        yield {"workload": "W8", "day": day, "edges": update.count(), "seconds": seconds}


WORKLOADS = {"W1": w1_preprocessing, "W2": w2_space, "W3": w3_static, "W4": w4_store_update, "W5": w5_match_update, "W6": w6_ablations, "W7": w7_estimates}


def report(rows: DataFrame) -> DataFrame:
    """Seconds by graph, pattern and method with all subtotals, from measurements as rows."""
    return rows.cube("graph", "pattern", "method").agg(F.sum("seconds").alias("seconds"), F.count("*").alias("runs"), F.grouping_id().alias("level"))


def run(spark: SparkSession, sf_dir: str, names: list[str]) -> Iterator[Row]:
    for graph in DATA_GRAPHS:
        wanted = [n for n in names if n in WORKLOADS]
        if wanted:
            edges = materialise(GRAPHS[graph](spark, sf_dir), f"edges-{graph}")
            for name in wanted:
                if name == "W6" and graph != "events_3d" or name == "W7" and graph == "events_seq":
                    continue
                yield from WORKLOADS[name](edges, graph)
    if "W8" in names:
        yield from w8_stream(spark, sf_dir)


def main() -> None:
    sf_dir = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01"
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for row in run(spark, sf_dir, sys.argv[2:] or [*WORKLOADS, "W8"]):
        print(json.dumps(row), flush=True)


if __name__ == "__main__":
    main()
