"""Counts of triangles, squares and diamonds without a store and without listing their matches, and triangles listed in slices.

A square is a pair of opposite vertices and two of their common neighbours: under the cover
of the two, which is not connected, all squares of a pair are one compressed match whose
two sets are equal, and n common neighbours make n (n - 1) / 2 squares. Of the two pairs of
a square the one that has its highest vertex by (degree, id) counts, so each square
counts once, and wedges open at a lower end of an edge, whatever the hubs are. A diamond is
an edge and two of the triangles on it.

Edges lie in tables bucketed by the end where wedges open, so wedges are met without an
exchange. They are the only rows that travel; their number is known from degrees before,
and they are counted in as many slices as keep one slice at ``WEDGES``, each a job of
its own whose shuffle files go when it ends. All slices together are all wedges.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise, materialise_bucketed
from motifmill.operators.store import both_ways, degrees, oriented

#: Wedges of a slice.
WEDGES = 1 << 26


def _bucketed(df: DataFrame, label: str, key: str) -> DataFrame:
    df.sparkSession.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")
    return materialise_bucketed(df, label, key, "zstd")


def _slices(wedges: DataFrame, most: int) -> int:
    """How many slices hold a measured number of wedges (n)."""
    return max(1, -(-int(wedges.first()[0] or 0) // most))


def _summed(slices: int, key: str, of: Callable[[Column], DataFrame]) -> DataFrame:
    """(n decimal): the sum of ``of(condition)``, a row (n) for each slice of ``key``."""
    parts = None
    for k in range(slices):
        mine = F.pmod(F.xxhash64(key, F.lit(7)), F.lit(slices)) == k if slices > 1 else F.lit(True)
        part = materialise(of(mine), "slice-count") if slices > 1 else of(mine)
        parts = part if parts is None else parts.unionByName(part)
    return parts.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("decimal(38,0)").alias("n"))


def _choose_two(n: str) -> Column:
    c = F.col(n).cast("decimal(38,0)")
    return F.sum((c * (c - 1) / 2).cast("decimal(38,0)")).cast("decimal(38,0)")


def _out_table(edges: DataFrame) -> DataFrame:
    # written before it is dealt, so that the shuffles of its joins are gone by then
    return _bucketed(materialise(oriented(edges), "oriented", "zstd"), "out", "x")


def _wedges_above(out: DataFrame) -> DataFrame:
    """(n): wedges that open at the end of lowest degree."""
    d = out.groupBy("x").agg(F.count("*").alias("d"))
    return d.agg(F.sum(F.expr("d * (d - 1) div 2")).alias("n"))


def _closed(out: DataFrame, mine: Column) -> DataFrame:
    """(x, y, z) of triangles whose middle end y is in a slice."""
    left = out.where(mine).select("x", "y", "dy")
    wedge = left.join(out.select("x", F.col("y").alias("z"), F.col("dy").alias("dz")).hint("merge"), "x").where(F.struct("dy", "y") < F.struct("dz", "z"))
    closing = out.select(F.col("x").alias("y"), F.col("y").alias("z")).where(mine)
    return wedge.select("x", "y", "z").join(closing, ["y", "z"])


def listed_triangles(edges: DataFrame, most: int = WEDGES) -> DataFrame:
    """(x, y, z) of all triangles, x < y < z, written slice by slice: only the wedges of one slice are on disk at a time."""
    out = _out_table(edges)
    slices, parts = _slices(_wedges_above(out), most), None
    t = F.sort_array(F.array("x", "y", "z"))
    for k in range(slices):
        mine = F.pmod(F.xxhash64("y", F.lit(7)), F.lit(slices)) == k if slices > 1 else F.lit(True)
        part = materialise(_closed(out, mine).select(t[0].alias("x"), t[1].alias("y"), t[2].alias("z")), "triangles", "zstd")
        parts = part if parts is None else parts.unionByName(part)
    return parts


def count_triangles(edges: DataFrame, most: int = WEDGES) -> DataFrame:
    """(n decimal): triangles."""
    out = _out_table(edges)
    return _summed(_slices(_wedges_above(out), most), "y", lambda mine: _closed(out, mine).agg(F.count("*").cast("decimal(38,0)").alias("n")))


def count_diamonds(edges: DataFrame, most: int = WEDGES) -> DataFrame:
    """(n decimal): pairs of triangles on an edge."""
    out = _out_table(edges)
    slices, on = _slices(_wedges_above(out), most), None
    for k in range(slices):
        mine = F.pmod(F.xxhash64("y", F.lit(7)), F.lit(slices)) == k if slices > 1 else F.lit(True)
        ends = [F.struct(F.col(u).alias("u"), F.col(v).alias("v")) for u, v in ("xy", "xz", "yz")]
        pairs = _closed(out, mine).select(F.inline(F.array(*ends)))
        part = pairs.groupBy("u", "v").agg(F.count("*").alias("t"))
        part = materialise(part, "edge-triangles") if slices > 1 else part
        on = part if on is None else on.unionByName(part)
    total = on.groupBy("u", "v").agg(F.sum("t").alias("t")) if slices > 1 else on
    return total.agg(F.coalesce(_choose_two("t"), F.lit(0)).cast("decimal(38,0)").alias("n"))


def count_squares(edges: DataFrame, most: int = WEDGES) -> DataFrame:
    """(n decimal): squares."""
    out = _out_table(edges)
    d = degrees(edges)
    ends = both_ways(edges).join(d.select(F.col("v").alias("n"), F.col("deg").alias("dn")), "n").select(F.col("v").alias("x"), "n", "dn")
    ends = _bucketed(ends, "ends", "x")
    bound = out.groupBy("x").agg(F.count("*").alias("a")).join(ends.groupBy("x").agg(F.count("*").alias("b")), "x").agg(F.sum(F.col("a") * F.col("b")).alias("n"))

    def of(mine: Column) -> DataFrame:
        tops = out.where(mine).select("x", "y", "dy")
        wedge = tops.join(ends.hint("merge"), "x").where(F.struct(F.col("dn").alias("d"), F.col("n").alias("i")) < F.struct(F.col("dy").alias("d"), F.col("y").alias("i")))
        return wedge.groupBy("y", "n").agg(F.count("*").alias("c")).agg(F.coalesce(_choose_two("c"), F.lit(0)).cast("decimal(38,0)").alias("n"))

    return _summed(_slices(bound, most), "y", of)


#: Patterns that are counted without listing them.
COUNTS = {"triangle": count_triangles, "square": count_squares, "diamond": count_diamonds}
