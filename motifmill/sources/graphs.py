"""Data graphs from tables, files and generators; all yield ``edges(u, v)`` with u < v, distinct."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def canonical_edges(pairs: DataFrame, u: str = "u", v: str = "v") -> DataFrame:
    """Undirected simple graph of pairs: directions folded, loops, nulls and repeats dropped."""
    a, b = F.col(u).cast("bigint"), F.col(v).cast("bigint")
    return pairs.where(a != b).select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v")).distinct()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _shared(members: DataFrame, group: str, member: str) -> DataFrame:
    """Pairs (x < y, group) of members of one group; ``members`` is distinct."""
    left, right = members.select(group, F.col(member).alias("x")), members.select(group, F.col(member).alias("y"))
    return left.join(right, group).where("x < y")


#: Ids of line vertices start here, above all document ids.
LINE_IDS = 1 << 60


def doc_lines(spark: SparkSession, sf_dir: str, least: int = 20, hub: int = 50) -> DataFrame:
    """Documents that share a trimmed line of 20 characters and more.

    A line of up to ``hub`` documents links each two of them. A more frequent one is a vertex itself, linked to each of
    its documents, so a line that a third of all documents have costs one edge a document and no pairs.
    """
    lines = table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    marks = lines.select("doc_id", F.trim("line").alias("line")).where(F.length("line") >= least).select("doc_id", F.md5("line").alias("h")).distinct()
    shared = marks.groupBy("h").count().where("count > 1")
    pairs = _shared(marks.join(shared.where(F.col("count") <= hub).select("h"), "h"), "h", "doc_id").select("x", "y")
    line = F.conv(F.substring("h", 1, 14), 16, 10).cast("bigint") + F.lit(LINE_IDS)
    hubs = marks.join(shared.where(F.col("count") > hub).select("h"), "h").select(F.col("doc_id").alias("x"), line.alias("y"))
    return canonical_edges(pairs.union(hubs), "x", "y")


def _next_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(ts, event_id, u, v): each event's user and the next event's user.

    The next event over the whole table needs its order: events are range-partitioned by time
    bucket for the window, and the first event of the following bucket joins the last of each.
    """
    events = table(spark, sf_dir, "events").select("ts", "event_id", "user_id").withColumn("day", F.date_trunc("hour", "ts"))
    within = Window.partitionBy("day").orderBy("ts", "event_id")
    inside = events.withColumn("next", F.lead("user_id").over(within))
    firsts = events.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first")).select("day", "first")
    follow = firsts.select("day", F.lead("first").over(Window.orderBy("day")).alias("after"))  # one row an hour
    return inside.join(follow, "day", "left").select("ts", "event_id", F.col("user_id").alias("u"), F.coalesce("next", "after").alias("v"))


def events_seq(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users of consecutive events."""
    return canonical_edges(_next_users(spark, sf_dir))


def events_3d(spark: SparkSession, sf_dir: str, before: str = "2024-01-04") -> DataFrame:
    """The same for events before a time."""
    return canonical_edges(_next_users(spark, sf_dir).where(F.col("ts") < F.lit(before).cast("timestamp")))


def copart(spark: SparkSession, sf_dir: str, orders: int = 1) -> DataFrame:
    """Parts that are together in ``orders`` orders and more."""
    members = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    pairs = _shared(members, "l_orderkey", "l_partkey").groupBy("x", "y").count().where(F.col("count") >= orders)
    return canonical_edges(pairs, "x", "y")


def copart_ge2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return copart(spark, sf_dir, 2)


def fk_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A triangle of order, part and supplier for each line item; ids 3k, 3k+1, 3k+2."""
    rows = table(spark, sf_dir, "lineitem").select((3 * F.col("l_orderkey")).alias("o"), (3 * F.col("l_partkey") + 1).alias("p"), (3 * F.col("l_suppkey") + 2).alias("s"))
    return canonical_edges(rows.select(F.inline(F.array(*[F.struct(F.col(x).alias("u"), F.col(y).alias("v")) for x, y in ("op", "os", "ps")]))))


def cust_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and the suppliers of their orders; bipartite."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", (2 * F.col("o_custkey")).alias("u"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", (2 * F.col("l_suppkey") + 1).alias("v"))
    return canonical_edges(orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")))


def emb_knn(spark: SparkSession, sf_dir: str, k: int = 5, blocks: int = 16) -> DataFrame:
    """Vectors and their ``k`` nearest by cosine, ties by the smaller id.

    Every vector is asked against all, in blocks: each block of queries meets each block of
    vectors in one Arrow task, and the best of the blocks are merged.
    """
    import numpy as np
    import pyarrow as pa

    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("id"), F.col("embedding").cast("array<float>").alias("x"))
    block = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
    asks = rows.select("id", "x", block.alias("q"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("c"), F.lit(True).alias("ask"))
    has = rows.select("id", "x", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("q"), block.alias("c"), F.lit(False).alias("ask"))

    def near(t: pa.Table) -> pa.Table:
        ask = t.column("ask").to_numpy(zero_copy_only=False)
        ids, x = t.column("id").to_numpy(), np.array(t.column("x").to_pylist(), dtype=np.float64).reshape(t.num_rows, -1)
        norm = np.linalg.norm(x, axis=1, keepdims=True)
        x = x / np.where(norm > 0, norm, 1)
        a, b = np.flatnonzero(ask), np.flatnonzero(~ask)
        u, v, s = [], [], []
        if len(a) and len(b):
            b = b[np.argsort(ids[b])]
            for i, sims in zip(a, x[a] @ x[b].T, strict=True):
                sims = np.where(ids[b] == ids[i], -2.0, np.round(sims, 9))
                top = np.argsort(-sims, kind="stable")[:k]
                top = top[sims[top] > -2]
                u += [int(ids[i])] * len(top)
                v += ids[b[top]].tolist()
                s += sims[top].tolist()
        return pa.table({"u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64()), "s": pa.array(s, pa.float64())})

    found = asks.union(has).groupBy("q", "c").applyInArrow(near, "u bigint, v bigint, s double")
    rank = F.row_number().over(Window.partitionBy("u").orderBy(F.desc("s"), "v"))
    return canonical_edges(found.withColumn("k", rank).where(F.col("k") <= k))


def emb_knn5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return emb_knn(spark, sf_dir, 5)


GRAPHS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "doc_lines": doc_lines,
    "events_3d": events_3d,
    "events_seq": events_seq,
    "copart_ge2": copart_ge2,
    "copart": copart,
    "fk_graph": fk_graph,
    "cust_supp": cust_supp,
    "emb_knn5": emb_knn5,
}

#: The same graphs in DuckDB's dialect, as bodies of a common table ``raw(u, v)``.
GRAPH_SQL = {
    "doc_lines": """WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents),
        m AS (SELECT DISTINCT doc_id, md5(trim(line, ' ')) AS h FROM l WHERE length(trim(line, ' ')) >= 20),
        k AS (SELECT h FROM m GROUP BY h HAVING count(*) BETWEEN 2 AND 50), j AS (SELECT h FROM m GROUP BY h HAVING count(*) > 50)
        SELECT a.doc_id AS u, b.doc_id AS v FROM m a JOIN m b USING (h) JOIN k USING (h) WHERE a.doc_id < b.doc_id
        UNION ALL SELECT doc_id, ('0x' || substr(h, 1, 14))::BIGINT + 1152921504606846976 FROM m JOIN j USING (h)""",
    "events_3d": "SELECT u, v FROM (SELECT ts, user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v FROM events) WHERE ts < TIMESTAMP '2024-01-04'",
    "events_seq": "SELECT user_id AS u, lead(user_id) OVER (ORDER BY ts, event_id) AS v FROM events",
    "copart_ge2": """WITH m AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem)
        SELECT a.l_partkey AS u, b.l_partkey AS v FROM m a JOIN m b USING (l_orderkey) WHERE a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) >= 2""",
    "copart": """WITH m AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem)
        SELECT a.l_partkey AS u, b.l_partkey AS v FROM m a JOIN m b USING (l_orderkey) WHERE a.l_partkey < b.l_partkey""",
    "fk_graph": """SELECT 3*l_orderkey AS u, 3*l_partkey+1 AS v FROM lineitem UNION SELECT 3*l_orderkey, 3*l_suppkey+2 FROM lineitem
        UNION SELECT 3*l_partkey+1, 3*l_suppkey+2 FROM lineitem""",
    "cust_supp": "SELECT 2*o_custkey AS u, 2*l_suppkey+1 AS v FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
}


def edges_sql(graph: str, name: str = "edges") -> str:
    """A common table ``name(u, v)`` of a graph's canonical edges."""
    return f"{name} AS (SELECT DISTINCT least(u, v)::BIGINT AS u, greatest(u, v)::BIGINT AS v FROM ({GRAPH_SQL[graph]}) WHERE u <> v)"


# -- files -----------------------------------------------------------------------


def read_edge_list(spark: SparkSession, path: str, comment: str = "#") -> DataFrame:
    """Text with two ids a line, separated by blanks, tabs or commas; comment lines and blank lines are skipped."""
    lines = spark.read.text(path).where(~F.col("value").startswith(comment))
    parts = F.split(F.trim("value"), r"[\s,]+")
    return canonical_edges(lines.select(F.try_element_at(parts, F.lit(1)).try_cast("bigint").alias("u"), F.try_element_at(parts, F.lit(2)).try_cast("bigint").alias("v")))


def read_edges_csv(spark: SparkSession, path: str, u: str = "u", v: str = "v") -> DataFrame:
    return canonical_edges(spark.read.csv(path, header=True), u, v)


def read_edges_json(spark: SparkSession, path: str, u: str = "u", v: str = "v") -> DataFrame:
    return canonical_edges(spark.read.schema(f"{u} bigint, {v} bigint").json(path), u, v)


def read_edges_parquet(spark: SparkSession, path: str, u: str = "u", v: str = "v") -> DataFrame:
    return canonical_edges(spark.read.parquet(path), u, v)


# -- generators --------------------------------------------------------------------


def complete_graph(spark: SparkSession, n: int) -> DataFrame:
    ids = F.explode(F.sequence(F.col("id") + 1, F.lit(n - 1)))
    return spark.range(max(n - 1, 0)).select(F.col("id").alias("u"), ids.alias("v"))


def star_graph(spark: SparkSession, leaves: int) -> DataFrame:
    return spark.range(1, leaves + 1).select(F.lit(0).cast("bigint").alias("u"), F.col("id").alias("v"))


def path_graph(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n - 1).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))


def complete_bipartite(spark: SparkSession, a: int, b: int) -> DataFrame:
    return spark.range(a).select(F.col("id").alias("u"), F.explode(F.sequence(F.lit(a).cast("bigint"), F.lit(a + b - 1).cast("bigint"))).alias("v"))


def random_graph(spark: SparkSession, n: int, pairs: int, seed: int = 0) -> DataFrame:
    """About ``pairs`` edges between uniform vertices, the same for a seed."""
    at = lambda k: F.pmod(F.xxhash64("id", F.lit(seed), F.lit(k)), F.lit(n))
    return canonical_edges(spark.range(pairs).select(at(1).alias("u"), at(2).alias("v")))


def power_law_graph(spark: SparkSession, n: int, pairs: int, exponent: float = 2.5, seed: int = 0) -> DataFrame:
    """Ends drawn so that degrees fall off with the exponent."""
    unit = lambda k: (F.pmod(F.xxhash64("id", F.lit(seed), F.lit(k)), F.lit(1 << 30)) + 1) / F.lit(float(1 << 30))
    at = lambda k: F.least(F.floor(F.lit(float(n)) * F.pow(unit(k), F.lit((exponent - 1) / (exponent - 2)))), F.lit(n - 1))
    return canonical_edges(spark.range(pairs).select(at(1).alias("u"), at(2).alias("v")))


# -- updates ------------------------------------------------------------------------


def update_batch(edges: DataFrame, size: int) -> DataFrame:
    """(batch_id, op, u, v): half of ``size`` deletes and half inserts, by arithmetic on ids instead of chance.

    Only the batch passes through ordered limits; ranks of vertices come from a window over vertex ids.
    """
    half = size // 2
    deletes = edges.orderBy(F.pmod(F.col("u") * 7919 + F.col("v") * 104729, F.lit(1000003)), "u", "v").limit(half).select(F.lit("-").alias("op"), "u", "v")
    vertices = edges.select("u").union(edges.select("v")).distinct()
    ranked = vertices.select((F.row_number().over(Window.orderBy("u")) - 1).cast("bigint").alias("rank"), F.col("u").alias("vertex"))
    n = vertices.count()
    if not n:
        return edges.limit(0).select(F.lit(0).alias("batch_id"), F.lit("+").alias("op"), "u", "v")
    i = F.col("id")
    draws = edges.sparkSession.range(20 * size).select(i.alias("i"), F.pmod(i * 48271 + 11, F.lit(n)).alias("a"), F.pmod(i * 69621 + 7919 * F.pmod(i, F.lit(97)) + 5, F.lit(n)).alias("b"))
    named = draws.join(ranked.select(F.col("rank").alias("a"), F.col("vertex").alias("x")), "a").join(ranked.select(F.col("rank").alias("b"), F.col("vertex").alias("y")), "b")
    pairs = named.where("x <> y").select("i", F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v")).groupBy("u", "v").agg(F.min("i").alias("i"))
    inserts = pairs.join(edges, ["u", "v"], "left_anti").orderBy("i").limit(half).select(F.lit("+").alias("op"), "u", "v")
    return deletes.union(inserts).select(F.lit(0).alias("batch_id"), "op", "u", "v")


def update_sql(size: int, edges: str = "edges") -> str:
    """Common tables ``gone(u, v)``, ``come(u, v)`` and ``later(u, v)`` of the same batch."""
    half = size // 2
    return f"""
gone AS (SELECT u, v FROM {edges} ORDER BY (u * 7919 + v * 104729) % 1000003, u, v LIMIT {half}),
vs AS (SELECT row_number() OVER (ORDER BY x) - 1 AS rank, x FROM (SELECT u AS x FROM {edges} UNION SELECT v FROM {edges})),
draws AS (SELECT i, (i * 48271 + 11) % (SELECT count(*) FROM vs) AS a, (i * 69621 + 7919 * (i % 97) + 5) % (SELECT count(*) FROM vs) AS b FROM range(0, {20 * size}) r(i)),
drawn AS (SELECT least(p.x, q.x) AS u, greatest(p.x, q.x) AS v, min(i) AS i FROM draws JOIN vs p ON p.rank = a JOIN vs q ON q.rank = b WHERE p.x <> q.x GROUP BY 1, 2),
come AS (SELECT u, v FROM drawn d WHERE NOT EXISTS (SELECT 1 FROM {edges} e WHERE e.u = d.u AND e.v = d.v) ORDER BY i LIMIT {half}),
later AS (SELECT u, v FROM {edges} EXCEPT SELECT u, v FROM gone UNION SELECT u, v FROM come)"""


def event_batches(spark: SparkSession, sf_dir: str, start: str = "2024-01-04", days: int = 3) -> DataFrame:
    """(batch_id, op, u, v): edges first seen on each of some days after ``start``."""
    pairs = _next_users(spark, sf_dir).where("u <> v").select("ts", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    first = pairs.groupBy("u", "v").agg(F.min("ts").alias("ts"))
    day = F.datediff(F.to_date("ts"), F.lit(start).cast("date"))
    return first.where((day >= 0) & (day < days)).select(day.cast("bigint").alias("batch_id"), F.lit("+").alias("op"), "u", "v")
