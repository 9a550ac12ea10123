"""Star contraction: what is computed in a round, and by how many workers at once."""

import random

from motifmill.llm import components as C


def test_each_write_contracts_once_and_apart_from_other_workers(spark, monkeypatch):
    plans = []
    inner = C.materialise

    def noted(df, label):
        plans.append(df._jdf.queryExecution().optimizedPlan().toString())
        return inner(df, label)

    monkeypatch.setattr(C, "materialise", noted)
    rng = random.Random(3)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(250)]
    parent = list(range(300))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for u, v in pairs:
        a, b = find(u), find(v)
        parent[max(a, b)] = min(a, b)
    links = spark.createDataFrame(pairs, "u long, v long").repartition(5).mapInArrow(lambda batches: batches, "u bigint, v bigint")
    got = {r.node: r.component for r in C.star_components(links).collect()}
    assert got == {x: find(x) for e in pairs if e[0] != e[1] for x in e}
    assert [p.count("MapInArrow") for p in plans] == [2] + [1] * (len(plans) - 1)
    first = [line for line in plans[0].splitlines() if "MapInArrow" in line or "Aggregate" in line]
    assert "Aggregate" in first[1]
