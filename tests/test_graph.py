"""The subgraph engine against brute force, closed forms and its own identities."""

import math
import random
from itertools import combinations, permutations

import duckdb
import pytest
from pyspark.sql import functions as F

from motifmill.api import SubgraphEngine, top_vertices
from motifmill.functions.scratch import materialise
from motifmill.operators import baselines as B
from motifmill.operators import compress as K
from motifmill.operators import incremental as I
from motifmill.operators import store as S
from motifmill.operators.join import compressed_join, plain_join, run_tree
from motifmill.operators.listing import check_unit_properties, degree_filter, list_unit, list_unit_compressed
from motifmill.plans import planner as L
from motifmill.plans.estimate import Sizes, degree_moments, epsilon, expected_matches, order_share, q_error, relaxed_matches
from motifmill.plans.pattern import PATTERNS, Pattern, anchors, automorphisms, decompositions, is_decomposition, min_units, named, restrict, symmetry_order, units, vertex_covers
from motifmill.sources import graphs as G

H = S.Partitioner(4)
DATA = "/root/testdata/sf0.001"
EDGES = "u bigint, v bigint"


def frame(spark, pairs):
    return spark.createDataFrame(sorted({(min(e), max(e)) for e in pairs if e[0] != e[1]}), EDGES)


def brute(pairs, p, order):
    """Every match by trying all choices."""
    near = {tuple(sorted(e)) for e in pairs}
    ids = sorted({x for e in near for x in e})
    out = set()
    for image in permutations(ids, len(p.vertices)):
        f = dict(zip(p.vertices, image, strict=True))
        if all(tuple(sorted((f[x], f[y]))) in near for x, y in p.edges) and all(f[x] < f[y] for x, y in order):
            out.add(image)
    return out


def rows(df):
    out = [tuple(tuple(x) if isinstance(x, list) else x for x in r) for r in df.collect()]
    assert len(out) == len(set(out))
    return set(out)


@pytest.fixture(scope="module")
def small(spark):
    rng = random.Random(2)
    pairs = {tuple(sorted(rng.sample(range(9), 2))) for _ in range(22)}
    edges = materialise(frame(spark, pairs), "edges")
    return pairs, edges, materialise(S.build_store(edges, H), "store")


@pytest.mark.parametrize("name", sorted(PATTERNS))
def test_pattern_algebra(name):
    p = named(name)
    order, all_maps = symmetry_order(p), automorphisms(p)
    assert sum(all(p.vertices.index(f[x]) < p.vertices.index(f[y]) for x, y in order) for f in all_maps) == 1
    assert order_share(p, order) * len(all_maps) == 1 == order_share(p, order, "linear_extension") * len(all_maps)
    for cover in vertex_covers(p):
        parts = min_units(p, cover)
        assert is_decomposition([q for _, q in parts], p, cover) and all(a in cover for a, _ in parts)
        for q in units(p, cover=cover)[:20]:
            assert cover & set(q.vertices) in [frozenset(c) for c in vertex_covers(q, connected=False)]  # a cover restricts to a cover


def test_joins_of_families():
    p = named("k4tri")
    order = symmetry_order(p)
    from motifmill.plans.estimate import Degrees

    sizes = Sizes(Degrees(1000, 5000, (10.0, 150.0, 4e3, 1e5), (10.0, 150.0, 4e3, 1e5)), order)
    joins = lambda family: L.optimal_tree(p, sizes, None, family).joins
    assert (joins("triangles"), joins("cliques"), joins("hub")) == (2, 1, 0)  # three overlapping triangles hold all edges
    assert min(len(d) for d in decompositions(named("square"))) == 2
    assert [L.left_deep_plans(named(n), frozenset(c))[1] for n, c in (("square", "abc"), ("two_triangles_bridge", "bcde"))] == [[[0, 1], [1, 0]], [[0, 1], [1, 0]]]


@pytest.mark.parametrize("name", ["square", "house", "diamond", "cycle5", "path4"])
def test_tree_is_optimal(name):
    from motifmill.plans.estimate import Degrees

    p = named(name)
    sizes = Sizes(Degrees(500, 2000, (8.0, 90.0, 1500.0, 3e4, 6e5), (8.0, 90.0, 1500.0, 3e4, 6e5)), symmetry_order(p))
    cover = L.best_cover(p, sizes)
    if len(p.edges) <= 5:
        assert math.isclose(L.optimal_tree(p, sizes, cover).cost, L.all_trees(p, sizes, cover))
    tree = L.optimal_tree(p, sizes, cover)
    assert math.isclose(L.cost_total(tree, 7.0, sizes, cover, decompress=False), 7.0 + tree.cost)


CLOSED = {"square": lambda n: 3 * math.comb(n, 4), "triangle": lambda n: math.comb(n, 3), "diamond": lambda n: 6 * math.comb(n, 4), "house": lambda n: 60 * math.comb(n, 5), "wheel4": lambda n: 15 * math.comb(n, 5), "k4tri": lambda n: 30 * math.comb(n, 5)}


def test_complete_graph(spark):
    engine = SubgraphEngine(spark, m=4, kind="mod").load(G.complete_graph(spark, 8))
    assert {name: engine.count(name) for name in CLOSED} == {name: f(8) for name, f in CLOSED.items()}
    assert S.space_actual(S.build_store(engine.edges, S.Partitioner(1)), S.Partitioner(1)).first().extra == 0


def test_triangle_free(spark):
    for edges in (G.star_graph(spark, 5), G.path_graph(spark, 6), G.complete_bipartite(spark, 3, 4)):
        store = S.build_store(edges, H)
        assert S.space_actual(store, H).first().extra == 0 and store.where("kind = 1").isEmpty()
    engine = SubgraphEngine(spark, m=3).load(G.complete_bipartite(spark, 3, 4))
    assert engine.count("square") == math.comb(3, 2) * math.comb(4, 2) and engine.count("triangle") == 0
    assert SubgraphEngine(spark).load(G.path_graph(spark, 4).limit(0)).count("house") == 0
    assert S.is_connected(G.path_graph(spark, 6)) and not S.is_connected(frame(spark, [(1, 2), (3, 4)]))


def test_store(spark, small):
    pairs, edges, store = small
    assert rows(S.build_store(edges, H, "ship")) == rows(store) == rows(S.unpack(S.pack(store)))
    for m in (1, 2, 3, 5):
        for kind in ("mod", "hash", "range"):
            h = S.Partitioner(m, kind, 8)
            assert S.space_actual(S.build_store(edges, h), h).first().extra <= S.space_bound(edges, m).first().bound
    near = lambda c: {x for e in pairs if c in e for x in e} | {c}
    assert rows(S.local_graph(edges, 3)) == {e for e in pairs if set(e) <= near(3)}
    merged = rows(S.merge_parts(store).select("part", "a", "b"))
    assert merged == {(c % 4, *e) for c in range(9) for e in pairs if set(e) <= near(c) and c in {x for y in pairs for x in y}}
    bits = {r.v: sorted(r.p) for r in S.partition_bitmaps(edges, S.Partitioner(40)).select("v", S.parts_of_bitmap(F.col("words"), 40).alias("p")).collect()}
    assert bits == {v: sorted({(set(e) - {v}).pop() % 40 for e in pairs if v in e}) for v in bits}


@pytest.mark.parametrize("name", ["triangle", "path3", "diamond", "star3", "fan4"])
def test_units(spark, small, name):
    pairs, edges, store = small
    p, order = named(name), symmetry_order(named(name))
    want = brute(pairs, p, order)
    truth = spark.createDataFrame(sorted(want), ", ".join(f"f_{v} bigint" for v in p.vertices))
    assert check_unit_properties(store, truth, p, order) == (True, True)
    assert rows(list_unit(store, p, order, engine="arrow_dfs")) == want
    if len(p.vertices) == 3:
        assert rows(list_unit(store, p, order, engine="hof")) == want
    assert rows(degree_filter(truth, S.degrees(edges), p)) == want
    for cover in vertex_covers(p):
        if anchors(p, cover):
            for how in ("group", "intersect"):
                cm = list_unit_compressed(store, p, cover, order, how=how)
                assert rows(K.decompress(cm, p, cover, order)) == want
                assert K.count_matches(cm, p, cover, order).first()[0] == len(want)


@pytest.mark.parametrize("name", ["square", "house", "cycle5", "two_triangles_bridge", "bowtie", "cycle6"])
def test_joins(spark, small, name):
    pairs, edges, store = small
    p, order = named(name), symmetry_order(named(name))
    want = brute(pairs, p, order)
    sizes = Sizes(degree_moments(S.degrees(edges)), order)
    for cover in [L.best_cover(p, sizes), vertex_covers(p)[0]]:
        tree = L.optimal_tree(p, sizes, cover)
        cm = materialise(run_tree(store, tree, cover, order), "cm")
        assert rows(K.decompress(cm, p, cover, order)) == want
        assert K.count_matches(cm, p, cover, order).first()[0] == len(want)
        for level in ("pairwise", "exact"):
            assert rows(K.decompress(K.prune(cm, p, cover, order, level), p, cover, order)) == want
        assert rows(K.decompress(K.split_sets(cm, p, cover, 2), p, cover, order)) == want
        if len(K.free(p, cover)) <= 2:
            whole = K.compress(K.decompress(cm, p, cover, order), p, cover)
            assert all(r.saved >= r.bound for r in K.saving(whole, p, cover, order).collect())
    truth = spark.createDataFrame(sorted(want), ", ".join(f"f_{v} bigint" for v in p.vertices))
    assert K.is_correct(cm, truth, p, cover, order)


def test_join_intersects_shared_sets(spark):
    p1, p2, cover = Pattern.parse("a-b a-d"), Pattern.parse("b-c c-d"), frozenset("abc")
    order = symmetry_order(named("square"))
    left = spark.createDataFrame([(1, 2, [4, 5, 9])], "s_a bigint, s_b bigint, c_d array<bigint>")
    right = spark.createDataFrame([(2, 3, [4, 5, 7])], "s_b bigint, s_c bigint, c_d array<bigint>")
    out = compressed_join(left, right, p1, p2, cover, order)
    assert [(r.s_a, r.s_b, r.s_c, r.c_d) for r in out.collect()] == [(1, 2, 3, [4, 5])]
    assert rows(K.decompress(out, named("square"), cover, order)) == {(1, 2, 3, 4), (1, 2, 3, 5)}
    with pytest.raises(ValueError):
        plain_join(left, right, Pattern.parse("a-b"), Pattern.parse("c-d"), order)


@pytest.mark.parametrize("name", ["triangle", "square", "house", "diamond", "k4tri"])
def test_rivals_agree(spark, small, name):
    pairs, edges, store = small
    p, order = named(name), symmetry_order(named(name))
    want = brute(pairs, p, order)
    sizes = Sizes(degree_moments(S.degrees(edges)), order)
    for rival in (B.StarCliqueBaseline(3), B.StarCliqueBaseline(4)):
        assert rows(rival.list(rival.prepare(edges), p, order, rival.plan(p, sizes))) == want
    rival = B.CliqueIndexBaseline()
    cm, core = rival.list(rival.prepare(edges), p, order)
    assert rows(K.decompress(cm, p, core, order)) == want
    assert rows(B.list_centralised(edges, p, order)) == want
    con = duckdb.connect()
    con.execute("create table edges(u bigint, v bigint)")
    con.executemany("insert into edges values (?, ?)", sorted(pairs))
    assert set(con.execute(B.brute_force_sql(p, order)).fetchall()) == want
    cliques = {r[0] for r in rows(B.list_cliques(edges, 3).select(F.sort_array(F.array("v1", "v2", "v3")).alias("c")))}
    assert cliques == {m for m in brute(pairs, named("triangle"), symmetry_order(named("triangle")))}


def random_update(rng, pairs, n=9):
    ops = [("-", *e) for e in rng.sample(sorted(pairs), 4)]
    ops += [("+", *rng.sample(range(n + 2), 2)) for _ in range(6)]
    return ops + [ops[0], ("+", 3, 3), ("-", 100, 101), ("+", *sorted(pairs)[0])]


@pytest.mark.parametrize("name", ["triangle", "square", "diamond", "house", "cycle6", "two_triangles_bridge"])
def test_updates(spark, small, name):
    pairs, edges, store = small
    rng = random.Random(len(name))
    ops = random_update(rng, pairs)
    update = spark.createDataFrame(ops, "op string, u bigint, v bigint")
    deleted, added = (materialise(x, "batch") for x in S.normalize_update(edges, update))
    now = (pairs - rows(deleted)) | rows(added)
    assert rows(deleted) <= pairs and not rows(added) & pairs
    new_edges = materialise(S.updated_edges(edges, deleted, added), "edges")
    new_store = materialise(S.update_store(store, S.adjacency(edges), deleted, added, H), "store")
    assert rows(new_edges) == now and rows(new_store) == rows(S.build_store(new_edges, H))
    p, order = named(name), symmetry_order(named(name))
    old, new = brute(pairs, p, order), brute(now, p, order)
    cover = L.best_cover(p, Sizes(degree_moments(S.degrees(edges)), order))
    cm = materialise(run_tree(store, L.optimal_tree(p, Sizes(degree_moments(S.degrees(edges)), order), cover), cover, order), "cm")
    assert rows(K.decompress(I.drop_removed(cm, p, deleted, cover), p, cover, order)) == old & new
    assert rows(I.drop_removed(K.decompress(cm, p, cover, order), p, deleted)) == old & new
    bitmaps = S.partition_bitmaps(new_edges, H)
    for how in ("intersect", "bitmap"):
        assert rows(K.decompress(I.patch_set(new_store, p, cover, order, added, H, how, bitmaps), p, cover, order)) == new - old  # each once
    assert rows(K.decompress(I.patch_set(new_store, p, cover, order, added, H, dedup="distinct"), p, cover, order)) == new - old
    if name in ("triangle", "square"):
        signed = rows(B.DeltaQueryBaseline().update(edges, deleted, added, p, order))
        assert signed == {(1, *m) for m in new - old} | {(-1, *m) for m in old - new}


def test_engine_over_batches(spark, small):
    pairs, edges, _ = small
    engine = SubgraphEngine(spark, m=3).load(edges)
    plan = engine.watch("square")
    now, rng = set(pairs), random.Random(9)
    for _ in range(2):
        ops = random_update(rng, now)
        changes = engine.apply(spark.createDataFrame(ops, "op string, u bigint, v bigint"), "bitmap")
        gone, come = {tuple(sorted(o[1:])) for o in ops if o[0] == "-"}, {tuple(sorted(o[1:])) for o in ops if o[0] == "+" and o[1] != o[2]}
        before, now = now, (now - (gone - come)) | come
        old, new = brute(before, plan.pattern, plan.order), brute(now, plan.pattern, plan.order)
        assert rows(engine.edges) == now and rows(engine.current("square")) == new
        patch, removed = changes[str(plan.pattern)]
        assert rows(patch) == new - old and rows(removed) == old - new
    assert "joins 1" in engine.explain("square") and engine.list("triangle", limit=1).count() <= 1
    assert top_vertices(engine.list("triangle"), 3).count() <= 3


def test_stream(spark, small, tmp_path):
    from motifmill.streaming.replay import Maintainer, read_updates

    pairs, edges, store = small
    p, order = named("diamond"), symmetry_order(named("diamond"))
    sizes = Sizes(degree_moments(S.degrees(edges)), order)
    cover = L.best_cover(p, sizes)
    keeper = Maintainer(spark, f"file://{tmp_path}/state", p, cover, order, H)
    keeper.start(edges, run_tree(store, L.optimal_tree(p, sizes, cover), cover, order))
    for e in ([(0, "+", 0, 20), (0, "+", 1, 20)], [(1, "-", *sorted(pairs)[0]), (1, "+", 2, 20)]):
        spark.createDataFrame(e, "batch_id bigint, op string, u bigint, v bigint").coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    keeper.run(read_updates(spark, f"{tmp_path}/in"), f"{tmp_path}/checkpoint")
    now = (set(pairs) - {sorted(pairs)[0]}) | {(0, 20), (1, 20), (2, 20)}
    assert rows(keeper.current()) == brute(now, p, order)
    again = keeper.state.read(keeper.last, "update")
    keeper.batch(spark.createDataFrame(again.collect(), again.schema), keeper.last)  # a replay changes nothing
    assert rows(keeper.current()) == brute(now, p, order)


def test_fixture_numbers(spark):
    edges = materialise(G.events_3d(spark, DATA), "edges")
    engine = SubgraphEngine(spark, m=16, kind="mod").load(edges)
    counts = {"triangle": 100, "square": 540, "diamond": 636, "house": 8203, "wheel4": 688, "k4tri": 1417, "path3": 503, "bowtie": 2051}
    assert {n: engine.count(n) for n in counts} == counts
    space = S.space_actual(engine.store, engine.h).first()
    assert (space.star, space.stored, space.extra) == (128, 428, 300)
    assert G.events_seq(spark, DATA).count() == 105 and G.doc_lines(spark, DATA).count() == 478
    batch = {o: n for o, n in G.update_batch(edges, 100).groupBy("op").count().collect()}
    assert batch == {"+": 41, "-": 50}


def test_estimates(spark):
    d = degree_moments(S.degrees(G.complete_graph(spark, 10)))
    p, order = named("triangle"), symmetry_order(named("triangle"))
    assert math.isclose(epsilon(p, d), (81 / 90) ** 3) and math.isclose(expected_matches(p, order, d), 720 / 6 * 0.9**3)
    assert relaxed_matches(p, d) >= expected_matches(p, order, d) and q_error(2, 8) == q_error(8, 2) == 4


@pytest.mark.parametrize("name", ["triangle", "diamond", "wheel4"])
def test_zero_join_plans_have_no_exchange(spark, name):
    """Compressed and plain listing as the queries run it, without broadcasts that would hide an exchange."""
    from motifmill.queries import Setting

    s = Setting(spark, DATA, "events_3d", name)
    assert s.tree.joins == 0
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        for found in (s.matches(), list_unit(s.store, s.p, s.order)):
            assert "Exchange" not in found._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.conf.unset("spark.sql.adaptive.enabled")


@pytest.mark.parametrize("graph", ["events_3d", "copart_ge2", "cust_supp"])
def test_joins_of_the_chosen_plans(spark, graph):
    """No join where one vertex is next to all others, one for square and house, whatever the graph's degrees."""
    sf_dir = "/root/testdata/sf0.01" if graph != "cust_supp" else DATA
    d = degree_moments(S.degrees(G.GRAPHS[graph](spark, sf_dir)))
    for name, joins in [("triangle", 0), ("diamond", 0), ("wheel4", 0), ("fan4", 0), ("clique4", 0), ("square", 1), ("house", 1), ("k4tri", 0)]:
        p = named(name)
        cover, tree = L.best_plan(p, Sizes(d, symmetry_order(p)))
        assert (name, tree.joins) == (name, joins) and all(x in cover or y in cover for x, y in p.edges)


def test_single_edge_stream(spark, small, tmp_path):
    """Every edge of an update as a batch of its own gives what one batch gives."""
    from motifmill.streaming.replay import Maintainer, apply_stream, one_edge_batches

    pairs, edges, _ = small
    p = named("triangle")
    order = symmetry_order(p)
    cover = min(vertex_covers(p, True), key=lambda c: (len(c), sorted(c)))
    gone, come = sorted(pairs)[0], next(e for e in combinations(range(9), 2) if e not in pairs)
    update = spark.createDataFrame([("-", *gone), ("+", *come), ("+", 3, 20)], "op string, u bigint, v bigint")
    assert len(list(one_edge_batches(update))) == 3
    keeper = Maintainer(spark, f"file://{tmp_path}/state", p, cover, order, H)
    tree = L.optimal_tree(p, Sizes(degree_moments(S.degrees(edges)), order), cover)
    keeper.start(edges, run_tree(S.build_store(edges, H), tree, cover, order))
    apply_stream(keeper, one_edge_batches(update))
    assert rows(keeper.current()) == brute((pairs - {gone}) | {come, (3, 20)}, p, order)


def test_sources(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n1 2\n2\t1\n3,3\n\n2 3\nx y\n")
    assert rows(G.read_edge_list(spark, str(tmp_path / "e.txt"))) == {(1, 2), (2, 3)}
    (tmp_path / "e.csv").write_text("u,v\n5,4\n4,5\n")
    assert rows(G.read_edges_csv(spark, str(tmp_path / "e.csv"))) == {(4, 5)}
    assert G.power_law_graph(spark, 200, 500).count() > 100 and G.random_graph(spark, 50, 100).count() > 50


def test_induced_and_vertices(spark, small):
    pairs, edges, _ = small
    kept = spark.createDataFrame([(v,) for v in range(5)], "v bigint")
    assert rows(S.induced_subgraph(edges, kept)) == {e for e in pairs if max(e) < 5}
    gone = S.delete_vertices(edges, spark.createDataFrame([(3,)], "v bigint"))
    assert {(r.u, r.v) for r in gone.collect()} == {e for e in pairs if 3 in e}
    assert restrict(frozenset({("a", "b"), ("b", "c")}), "ab") == {("a", "b")} and list(combinations("ab", 2))
