"""What queries on updates write: neighbourhoods of the update, and triangles in slices, but no store of the whole graph."""

import pytest

from motifmill import queries as Q
from motifmill.operators import incremental as I
from motifmill.operators.counting import listed_triangles
from motifmill.plans.pattern import named

#: Not read: the graph is made here.
SF = "/root/testdata/sf0.001"


@pytest.fixture()
def written(monkeypatch):
    """Rows of each table that is written bucketed."""
    rows = []
    inner = Q.materialise_bucketed

    def counted(df, label, key):
        out = inner(df, label, key)
        rows.append(out.count())
        return out

    monkeypatch.setattr(Q, "materialise_bucketed", counted)
    return rows


def test_reach_of_patterns():
    assert [I.reach(named(p)) for p in ("triangle", "square", "diamond", "house", "wheel4", "two_triangles_bridge")] == [0, 1, 1, 1, 1, 3]


@pytest.fixture()
def apart(monkeypatch):
    """A graph of 300 triangles that share nothing."""

    def graph(spark, sf_dir):
        return spark.createDataFrame([(3 * k + a, 3 * k + b) for k in range(300) for a, b in ((0, 1), (0, 2), (1, 2))], "u long, v long")

    monkeypatch.setitem(Q.GRAPHS, "apart", graph)


def test_removed_matches_store_only_what_is_near_the_deleted_edges(spark, written, apart):
    got = Q.removed_query(spark, SF, "apart", "triangle").collect()
    assert 17 <= len(got) == len(set(got)) <= 50
    assert len(written) == 1 and written[0] <= 9 * 50


@pytest.mark.parametrize("query", [lambda spark: Q.update_store_query(spark, SF, "apart"), lambda spark: Q.updated_query(spark, SF, "apart", "triangle")])
def test_updates_write_no_whole_store(spark, written, apart, query):
    assert query(spark).count() > 0
    assert all(rows < 2 * 900 for rows in written)


def test_triangles_listed_in_one_slice_and_in_many(spark):
    edges = [(u, v) for u in range(12) for v in range(u + 1, 12) if (u * v) % 5 != 2]
    frame = spark.createDataFrame(edges, "u long, v long")
    held = set(edges)
    want = sorted((x, y, z) for x, y in edges for z in range(y + 1, 12) if (x, z) in held and (y, z) in held)
    for most in (1 << 26, 20):
        assert sorted(tuple(r) for r in listed_triangles(frame, most).collect()) == want
