"""Matches of hub units, straight from the store.

All joins are on the center, alone or with further columns, so a store that is
bucketed by center needs no exchange; conditions on ids are applied as soon as both
columns are there.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifmill.operators.compress import all_of, clean_sets, compress, free, kept, pair_condition
from motifmill.operators.store import INNER, STAR, pack
from motifmill.plans.pattern import Order, Pattern, pick_anchor, restrict


def visit_order(q: Pattern, anchor: str, cover: frozenset[str] | None = None) -> list[str]:
    """Vertices after the anchor: next the one with most bound neighbours, those of the cover first among equals."""
    bound, out = {anchor}, []
    while len(out) < len(q.vertices) - 1:
        rest = [v for v in q.vertices if v not in bound]
        v = max(rest, key=lambda v: (len(q.neighbours[v] & bound), cover is None or v in cover, [-ord(c) for c in v]))
        bound.add(v)
        out.append(v)
    return out


def _stars(store: DataFrame) -> DataFrame:
    return store.where(F.col("kind") == STAR).select("center", F.col("b").alias("n"))


def _inner_both(store: DataFrame) -> DataFrame:
    inner = store.where(F.col("kind") == INNER).select("center", "a", "b")
    return inner.select("center", F.inline(F.array(F.struct(F.col("a").alias("x"), F.col("b").alias("y")), F.struct(F.col("b").alias("x"), F.col("a").alias("y")))))


def list_vertices(store: DataFrame, q: Pattern, anchor: str, wanted: list[str], order: Order, prefix: str = "f_") -> DataFrame:
    """(center, prefix+anchor, prefix+v ...): images of some of a unit's vertices with all edges among them."""
    part = q.induced(set(wanted) | {anchor})
    stars, inner = _stars(store), _inner_both(store)
    out = stars.select("center").distinct().withColumn(prefix + anchor, F.col("center"))
    bound = [anchor]
    for v in visit_order(part, anchor) if len(wanted) > 0 else []:
        name = prefix + v
        inside = [w for w in bound if w != anchor and part.has(v, w)]
        if inside:
            first, *more = inside
            out = out.join(inner.select("center", F.col("x").alias(prefix + first), F.col("y").alias(name)), ["center", prefix + first])
            for w in more:
                out = out.join(inner.select("center", F.col("x").alias(prefix + w), F.col("y").alias(name)), ["center", prefix + w, name], "left_semi")
        else:
            out = out.join(stars.select("center", F.col("n").alias(name)), "center")
        out = out.where(all_of([pair_condition(w, v, F.col(prefix + w), F.col(name), order) for w in bound]))
        bound.append(v)
    return out


def list_unit(store: DataFrame, q: Pattern, order: Order, anchor: str | None = None, engine: str = "relational") -> DataFrame:
    """All plain matches of a hub unit, at the images of its anchor.

    ``relational``: joins on the center; ``arrow_dfs``: backtracking inside each packed
    center in Arrow batches; ``hof``: the pattern of three vertices by array functions.
    """
    anchor = anchor or pick_anchor(q)
    order = restrict(order, q.vertices)
    names = [f"f_{v}" for v in q.vertices]
    if engine == "relational":
        return list_vertices(store, q, anchor, [v for v in q.vertices if v != anchor], order).select(names)
    if engine == "arrow_dfs":
        return _list_dfs(store, q, order, anchor)
    if engine == "hof" and len(q.vertices) == 3:
        return _list_hof(store, q, order, anchor)
    raise ValueError(engine)


def _list_dfs(store: DataFrame, q: Pattern, order: Order, anchor: str) -> DataFrame:
    import pyarrow as pa

    steps = visit_order(q, anchor)
    names = [f"f_{v}" for v in q.vertices]
    before = {v: [w for w in [anchor, *steps[:k]]] for k, v in enumerate(steps)}
    near = {v: [w for w in before[v] if w != anchor and q.has(v, w)] for v in steps}
    less = {(x, y) for x, y in order}

    def run(batches):
        for batch in batches:
            out = {v: [] for v in q.vertices}
            for center, nbrs, inner in zip(*[batch.column(k).to_pylist() for k in range(3)], strict=True):
                local: dict[int, set[int]] = {}
                for e in inner or []:
                    local.setdefault(e["a"], set()).add(e["b"])
                    local.setdefault(e["b"], set()).add(e["a"])
                image = {anchor: center}

                def extend(k: int, image=image, nbrs=nbrs, local=local) -> None:
                    if k == len(steps):
                        for v in q.vertices:
                            out[v].append(image[v])
                        return
                    v = steps[k]
                    pool = set.intersection(*[local.get(image[w], set()) for w in near[v]]) if near[v] else nbrs
                    for n in pool:
                        if all(n != image[w] and ((w, v) not in less or image[w] < n) and ((v, w) not in less or n < image[w]) for w in before[v]):
                            image[v] = n
                            extend(k + 1)
                            del image[v]

                extend(0)
            yield pa.RecordBatch.from_arrays([pa.array(out[v], pa.int64()) for v in q.vertices], names)

    return pack(store).select("center", "nbrs", "inner").mapInArrow(run, ", ".join(f"{n} bigint" for n in names))


def _list_hof(store: DataFrame, q: Pattern, order: Order, anchor: str) -> DataFrame:
    x, y = [v for v in q.vertices if v != anchor]
    packed = pack(store)
    if q.has(x, y):
        pairs = F.flatten(F.transform("inner", lambda e: F.array(F.struct(e["a"].alias(f"f_{x}"), e["b"].alias(f"f_{y}")), F.struct(e["b"].alias(f"f_{x}"), e["a"].alias(f"f_{y}")))))
    else:
        pairs = F.flatten(F.transform("nbrs", lambda a: F.transform("nbrs", lambda b: F.struct(a.alias(f"f_{x}"), b.alias(f"f_{y}")))))
    out = packed.select(F.col("center").alias(f"f_{anchor}"), F.inline(pairs))
    conditions = [pair_condition(v, w, F.col(f"f_{v}"), F.col(f"f_{w}"), order) for k, v in enumerate(q.vertices) for w in q.vertices[k + 1 :]]
    return out.where(all_of(conditions)).select(*[f"f_{v}" for v in q.vertices])


def list_unit_compressed(store: DataFrame, q: Pattern, cover: frozenset[str], order: Order, anchor: str | None = None, how: str = "intersect", only: DataFrame | None = None) -> DataFrame:
    """Compressed matches of a unit whose anchor is in the cover; ``only`` names images of some cover vertices that are wanted.

    ``group`` lists plain matches and groups them by skeleton. ``intersect`` lists only
    images of the cover and takes each other vertex's candidates as the intersection of
    its cover neighbours' lists at that center: no match is enumerated.
    """
    cover = cover & set(q.vertices)
    anchor = anchor or pick_anchor(q, cover)
    order = restrict(order, q.vertices)
    columns = [f"s_{v}" for v in kept(q, cover)] + [f"c_{v}" for v in free(q, cover)]
    if how == "group":
        out = compress(list_unit(store, q, order, anchor), q, cover).select(columns)
        return out if only is None else out.join(only, only.columns, "left_semi")
    out = list_vertices(store, q, anchor, [v for v in kept(q, cover) if v != anchor], order, "s_")
    if only is not None:
        out = out.join(only, only.columns, "left_semi")  # before any candidate set is built
    lists = None
    for y in free(q, cover):
        sources = [x for x in sorted(q.neighbours[y]) if x != anchor]
        if not sources:
            nbrs = _stars(store).groupBy("center").agg(F.sort_array(F.collect_list("n")).alias(f"c_{y}"))
            out = out.join(nbrs, "center")
        for k, x in enumerate(sources):
            lists = lists or _inner_both(store).groupBy("center", "x").agg(F.sort_array(F.collect_list("y")).alias("l"))
            out = out.join(lists.select("center", F.col("x").alias(f"s_{x}"), F.col("l").alias(f"l_{k}")), ["center", f"s_{x}"])
            out = out.withColumn(f"c_{y}", F.array_intersect(f"c_{y}", f"l_{k}") if k else F.col(f"l_{k}")).drop(f"l_{k}")
    return clean_sets(out, q, cover, order).select(columns)


def list_units(store: DataFrame, parts: list[Pattern], cover: frozenset[str], order: Order, how: str = "intersect") -> list[DataFrame]:
    """Several units from one store, which is scanned from one table or cached plan."""
    return [list_unit_compressed(store, q, cover, order, how=how) for q in parts]


def degree_filter(matches: DataFrame, deg: DataFrame, p: Pattern) -> DataFrame:
    """Plain matches whose vertices have at least their pattern vertex's degree; true of all real matches."""
    for v in p.vertices:
        d = deg.select(F.col("v").alias(f"f_{v}"), F.col("deg").alias("d")).where(F.col("d") >= p.degree(v)).select(f"f_{v}")
        matches = matches.join(d, f"f_{v}", "left_semi")
    return matches.select(*[f"f_{v}" for v in p.vertices])


def check_unit_properties(store: DataFrame, edges_truth: DataFrame, q: Pattern, order: Order) -> tuple[bool, bool]:
    """(complete, independent): parts together list all matches of ``edges_truth``, and no match twice."""
    found = list_unit(store, q, order)
    missing = edges_truth.exceptAll(found)
    twice = found.groupBy(*found.columns).count().where("count > 1")
    return missing.isEmpty() and found.exceptAll(edges_truth).isEmpty(), twice.isEmpty()
