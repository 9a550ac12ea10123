"""Matches in plain and compressed form.

Plain: a column ``f_<vertex>`` for each pattern vertex. Compressed by a vertex cover:
``s_<vertex>`` for the cover's vertices, which make up the skeleton, and
``c_<vertex>``, a sorted array of candidates, for each other one. A row stands for all
choices of one candidate for each set that are distinct and keep the order; no two
vertices outside a cover are adjacent, so nothing else restricts the choice.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifmill.plans.pattern import Order, Pattern


def kept(p: Pattern, cover: frozenset[str]) -> list[str]:
    return [v for v in p.vertices if v in cover]


def free(p: Pattern, cover: frozenset[str]) -> list[str]:
    return [v for v in p.vertices if v not in cover]


def all_of(conditions: list[Column]) -> Column:
    return reduce(lambda a, b: a & b, conditions, F.lit(True))


def pair_condition(x: str, y: str, a: Column, b: Column, order: Order) -> Column:
    """That the images of x and y are distinct and keep the order."""
    if (x, y) in order:
        return a < b
    return b < a if (y, x) in order else a != b


def valid(vertices: list[str], order: Order, prefix: str = "f_") -> Column:
    """All images distinct, and in order."""
    return all_of([pair_condition(x, y, F.col(prefix + x), F.col(prefix + y), order) for k, x in enumerate(vertices) for y in vertices[k + 1 :]])


def _fits(y: str, skeleton: list[str], order: Order):
    return lambda u: all_of([pair_condition(x, y, F.col(f"s_{x}"), u, order) for x in skeleton])


def _has_partners(x: str, others: list[str], order: Order, exact: bool):
    def one(y: str, u: Column) -> Column:
        return F.exists(f"c_{y}", lambda w: pair_condition(x, y, u, w, order))

    def choice(u: Column) -> Column:
        a, b = others
        rest = lambda w: F.exists(f"c_{b}", lambda t: pair_condition(x, b, u, t, order) & pair_condition(a, b, w, t, order))
        return F.exists(f"c_{a}", lambda w: pair_condition(x, a, u, w, order) & rest(w))

    return choice if exact and len(others) == 2 else lambda u: all_of([one(y, u) for y in others])


def clean_sets(cm: DataFrame, p: Pattern, cover: frozenset[str], order: Order) -> DataFrame:
    """Takes skeleton images and candidates out of order from the sets; rows with an empty set go."""
    skeleton = kept(p, cover)
    for y in free(p, cover):
        cm = cm.withColumn(f"c_{y}", F.filter(f"c_{y}", _fits(y, skeleton, order))).where(F.size(f"c_{y}") > 0)
    return cm


def prune(cm: DataFrame, p: Pattern, cover: frozenset[str], order: Order, level: str = "pairwise") -> DataFrame:
    """``skeleton``: against the skeleton; ``pairwise``: also candidates without a partner in another set; ``exact``: without a full choice (up to three sets)."""
    cm = clean_sets(cm, p, cover, order)
    sets = free(p, cover)
    if level == "skeleton" or len(sets) < 2:
        return cm
    for x in sets:
        others = [y for y in sets if y != x]
        cm = cm.withColumn(f"p_{x}", F.filter(f"c_{x}", _has_partners(x, others, order, level == "exact")))
    for x in sets:
        cm = cm.withColumn(f"c_{x}", F.col(f"p_{x}")).drop(f"p_{x}")
    return cm.where(all_of([F.size(f"c_{x}") > 0 for x in sets]))


def compress(plain: DataFrame, p: Pattern, cover: frozenset[str]) -> DataFrame:
    """Groups plain matches by skeleton."""
    keys = [F.col(f"f_{v}").alias(f"s_{v}") for v in kept(p, cover)]
    sets = [F.sort_array(F.collect_set(f"f_{v}")).alias(f"c_{v}") for v in free(p, cover)]
    return plain.groupBy(*keys).agg(*sets) if sets else plain.select(*keys).distinct()


def fragments(plain: DataFrame, p: Pattern, cover: frozenset[str]) -> DataFrame:
    """Compressed rows of any set of plain matches.

    All matches of a skeleton are a product of sets only if the set is complete, as a
    patch is not; so only the last free vertex is gathered, and the other sets hold one.
    """
    sets = free(p, cover)
    if not sets:
        return compress(plain, p, cover)
    *single, last = sets
    keys = [F.col(f"f_{v}").alias(f"s_{v}") for v in kept(p, cover)] + [F.array(f"f_{v}").alias(f"c_{v}") for v in single]
    return plain.groupBy(*keys).agg(F.sort_array(F.collect_set(f"f_{last}")).alias(f"c_{last}"))


def decompress(cm: DataFrame, p: Pattern, cover: frozenset[str], order: Order) -> DataFrame:
    """All plain matches of compressed rows, checking distinctness and order of the free vertices."""
    out = cm.select(*[F.col(f"s_{v}").alias(f"f_{v}") for v in kept(p, cover)], *[f"c_{v}" for v in free(p, cover)])
    done = list(kept(p, cover))
    for v in free(p, cover):
        out = out.withColumn(f"f_{v}", F.explode(f"c_{v}")).drop(f"c_{v}")
        out = out.where(all_of([pair_condition(x, v, F.col(f"f_{x}"), F.col(f"f_{v}"), order) for x in done]))
        done.append(v)
    return out.select(*[f"f_{v}" for v in p.vertices])


def row_count(p: Pattern, cover: frozenset[str], order: Order) -> Column:
    """Matches of a row with at most two sets."""
    sets = free(p, cover)
    if not sets:
        return F.lit(1).cast("bigint")
    if len(sets) == 1:
        return F.size(f"c_{sets[0]}").cast("bigint")
    x, y = sets
    a, b = F.col(f"c_{x}"), F.col(f"c_{y}")
    if (x, y) not in order and (y, x) not in order:
        return F.size(a).cast("bigint") * F.size(b) - F.size(F.array_intersect(a, b))
    if (y, x) in order:
        a, b = b, a
    n = F.size(a).cast("bigint")
    ordered = F.aggregate(a, F.lit(0).cast("bigint"), lambda s, u: s + F.size(F.filter(b, lambda w: w > u)))
    return F.when(a == b, (n * (n - 1) / 2).cast("bigint")).otherwise(ordered)


def count_matches(cm: DataFrame, p: Pattern, cover: frozenset[str], order: Order) -> DataFrame:
    """(matches decimal(38,0)) without decompressing; of three sets and more all but two are opened."""
    cm, cover = open_sets(cm, p, cover, order, 2)
    return cm.agg(F.coalesce(F.sum(row_count(p, cover, order).cast("decimal(38,0)")), F.lit(0)).cast("decimal(38,0)").alias("matches"))


def open_sets(cm: DataFrame, p: Pattern, cover: frozenset[str], order: Order, left: int) -> tuple[DataFrame, frozenset[str]]:
    """Opens sets until at most ``left`` remain; opened vertices join the cover."""
    while len(free(p, cover)) > left:
        v = free(p, cover)[0]
        cm = cm.withColumn(f"s_{v}", F.explode(f"c_{v}")).drop(f"c_{v}")
        cover = cover | {v}
        cm = clean_sets(cm, p, cover, order)
    return cm, cover


def is_correct(cm: DataFrame, truth: DataFrame, p: Pattern, cover: frozenset[str], order: Order) -> bool:
    """Whether the rows stand for exactly the plain matches of ``truth``, each once."""
    mine, theirs = decompress(cm, p, cover, order), truth.select(*[f"f_{v}" for v in p.vertices])
    return mine.exceptAll(theirs).isEmpty() and theirs.exceptAll(mine).isEmpty()


def saving(cm: DataFrame, p: Pattern, cover: frozenset[str], order: Order) -> DataFrame:
    """For each row: ``matches``, integers ``saved`` against plain storage, and the ``bound`` a (matches - 1)."""
    a, sets = len(kept(p, cover)), free(p, cover)
    held = sum((F.size(f"c_{v}") for v in sets), F.lit(0)) + a
    n = row_count(p, cover, order)
    return cm.select(*[f"s_{v}" for v in kept(p, cover)], n.alias("matches"), (n * len(p.vertices) - held).alias("saved"), (a * (n - 1)).alias("bound"))


def stored_ints(cm: DataFrame, p: Pattern, cover: frozenset[str]) -> DataFrame:
    """(skeleton_ints, set_ints, rows)."""
    held = sum((F.size(f"c_{v}") for v in free(p, cover)), F.lit(0))
    return cm.agg(
        (F.count("*") * len(kept(p, cover))).alias("skeleton_ints"), F.coalesce(F.sum(held), F.lit(0)).cast("bigint").alias("set_ints"), F.count("*").alias("rows")
    )


def ratio(cm: DataFrame, p: Pattern, cover: frozenset[str], order: Order) -> DataFrame:
    """(matches, ints, ratio): plain integers over compressed integers."""
    held = sum((F.size(f"c_{v}") for v in free(p, cover)), F.lit(len(kept(p, cover))))
    opened = cm.agg(F.coalesce(F.sum(held), F.lit(0)).cast("bigint").alias("ints"))
    both = count_matches(cm, p, cover, order).select(F.col("matches").cast("bigint").alias("matches")).join(opened)
    return both.withColumn("ratio", F.when(F.col("ints") > 0, F.col("matches") * len(p.vertices) / F.col("ints")))


def split_sets(cm: DataFrame, p: Pattern, cover: frozenset[str], most: int) -> DataFrame:
    """Rows whose sets have at most ``most`` candidates: a longer set is cut, and each piece makes a row of its own."""
    for v in free(p, cover):
        starts = F.sequence(F.lit(1), F.size(f"c_{v}"), F.lit(most))
        cm = cm.withColumn("__at", F.explode(starts)).withColumn(f"c_{v}", F.slice(f"c_{v}", F.col("__at"), F.lit(most))).drop("__at")
    return cm
