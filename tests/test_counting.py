"""Counts without listing against the matches that are listed."""

import random
from itertools import combinations

import pytest

from motifmill.operators.counting import COUNTS


def graph():
    rng = random.Random(11)
    edges = {(0, v) for v in range(1, 40)} | {(v, v + 100) for v in range(20)}
    edges |= {tuple(sorted(rng.sample(range(40), 2))) for _ in range(160)}
    return sorted(edges)


def truth(edges):
    near = {}
    for u, v in edges:
        near.setdefault(u, set()).add(v)
        near.setdefault(v, set()).add(u)
    both = lambda u, v: len(near[u] & near[v])
    two = lambda n: n * (n - 1) // 2
    return {
        "triangle": sum(both(u, v) for u, v in edges) // 3,
        "square": sum(two(both(u, v)) for u, v in combinations(sorted(near), 2)) // 2,
        "diamond": sum(two(both(u, v)) for u, v in edges),
    }


@pytest.mark.parametrize("pattern", ["triangle", "square", "diamond"])
def test_counts_in_one_slice_and_in_many(spark, pattern):
    edges = graph()
    frame = spark.createDataFrame(edges, "u long, v long")
    want = truth(edges)[pattern]
    assert want > 0
    assert int(COUNTS[pattern](frame).first()[0]) == want
    assert int(COUNTS[pattern](frame, most=500).first()[0]) == want
    assert int(COUNTS[pattern](frame.limit(0)).first()[0]) == 0


def test_square_count_of_the_query_lists_nothing(spark):
    """The plan of the count has no arrays of candidates and one exchange of wedges."""
    from motifmill.queries import queries

    plan = queries()["count_square_cust_supp"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "collect_list" not in plan and "array_intersect" not in plan


def test_bushy_patch_reads_each_node_from_what_was_written(spark):
    """The plan at the root scans written matches and lists no unit again."""
    from motifmill.queries import queries

    plan = queries()["baseline_bushy_patch_square"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
    assert "collect_list" not in plan
