"""Readers, sinks, table functions, reports and the contract of the entry module."""

import json
import subprocess
import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from motifmill import workloads
from motifmill.functions.scratch import materialise
from motifmill.functions.udtf import register
from motifmill.operators import store as S
from motifmill.sources import graphs as G
from motifmill.sources.sinks import read_matches, run_only, write_matches

ROOT = Path(__file__).resolve().parents[1]
DATA = "/root/testdata/sf0.001"


def test_sinks(spark, tmp_path):
    rows = spark.createDataFrame([(1, 2, 3)], "f_a bigint, f_b bigint, f_c bigint")
    for _ in range(2):  # a replay writes over its batch
        write_matches(rows, str(tmp_path / "m"), 4)
    assert [(r.f_a, r.batch_id) for r in read_matches(spark, str(tmp_path / "m")).collect()] == [(1, 4)]
    run_only(rows)


def test_table_functions(spark):
    register(spark)
    edges = G.complete_graph(spark, 5)
    S.pack(S.build_store(edges, S.Partitioner(2))).createOrReplaceTempView("packed")
    found = spark.sql("select t.* from packed, lateral unit_triangles(center, inner) t where f_a < f_b and f_b < f_c")
    assert found.count() == 10
    assert spark.sql("select * from values (array(array(1, 2), array(2, 3))) as s(sets), lateral decompress_sets(sets)").count() == 3


def test_sql_front(spark):
    from motifmill.api import subgraphs

    G.complete_graph(spark, 5).createOrReplaceTempView("k5")
    subgraphs(spark, "k5", "a-b,b-c,a-c", "found")
    assert spark.sql("select count(*) from found").first()[0] == 10


@pytest.mark.parametrize("name", ["W1", "W2", "W4", "W7"])
def test_workloads(spark, name):
    edges = materialise(G.events_3d(spark, DATA), "edges")
    out = list(workloads.WORKLOADS[name](edges, "events_3d"))
    assert out and all(r["workload"] == name for r in out)
    json.dumps(out)


def test_measures(spark):
    from motifmill.functions.metrics import measure

    spent = measure(spark, lambda: run_only(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count()))
    assert spent["shuffleWriteRecords"] >= 7 and spent["shuffleWriteBytes"] > 0 and spent["seconds"] > 0


def test_report(spark):
    rows = spark.createDataFrame([("g", "p", "a", 1.0), ("g", "p", "b", 2.0)], "graph string, pattern string, method string, seconds double")
    total = workloads.report(rows).where("level = 7").first()
    assert (total.seconds, total.runs) == (3.0, 2)


def test_sliding_window(spark):
    from motifmill.streaming.replay import sessions, sliding_updates

    pairs = spark.createDataFrame([(0, 1, 2), (1, 2, 3), (3, 1, 2), (3, 3, 3)], "day bigint, u bigint, v bigint")
    batch = sliding_updates(pairs, 2)
    assert {tuple(r) for r in batch(2).collect()} == {("-", 1, 2)} and {tuple(r) for r in batch(3).collect()} == {("-", 2, 3), ("+", 1, 2)}
    events = spark.createDataFrame([(1, "2024-01-01 00:00:00"), (1, "2024-01-01 00:10:00"), (1, "2024-01-01 02:00:00")], "user_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp"))
    assert sessions(events).count() == 2


def test_watermarked_stream(spark, tmp_path):
    from motifmill.streaming.replay import event_edges

    spark.read.parquet(f"{DATA}/events.parquet").select("ts", "user_id").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("ts timestamp, user_id bigint").parquet(str(tmp_path / "in"))
    query = event_edges(stream).writeStream.format("memory").queryName("daily").outputMode("append").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    query.awaitTermination()
    assert spark.table("daily").count() > 0


def test_works_without_the_training_data_operators(tmp_path):
    """The entry module imports, and its other queries are there, when ``llm`` and the pipeline are deleted."""
    code = "import __spark_entry__ as e; q = e.queries(); assert 'list_house_events_3d' in q; assert not [n for n in q if n.startswith('op')]; assert set(e.oracle_sql()) <= set(q)"
    import shutil

    shutil.copytree(ROOT / "motifmill", tmp_path / "motifmill", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)})
    assert done.returncode == 0, done.stderr[-800:]


def test_nothing_imports_llm():
    users = [p for p in (ROOT / "motifmill").rglob("*.py") if "llm" not in p.relative_to(ROOT).parts and "motifmill.llm" in p.read_text()]
    assert users == []
