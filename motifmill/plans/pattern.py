"""Patterns and their algebra: small graphs on the driver, no Spark job.

A pattern is a connected simple graph with named vertices. A piece of a pattern is
a pattern made of some of its edges. An order is a set of pairs (x, y): the image of
x has the smaller id.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property
from itertools import combinations, permutations

Edge = tuple[str, str]
Order = frozenset[Edge]


@dataclass(frozen=True)
class Pattern:
    """Edges are sorted pairs; vertices follow from them."""

    edges: tuple[Edge, ...]

    @classmethod
    def of(cls, edges) -> Pattern:
        pairs = {tuple(sorted(e)) for e in edges}
        if any(x == y for x, y in pairs):
            raise ValueError("a pattern has no loops")
        return cls(tuple(sorted(pairs)))

    @classmethod
    def parse(cls, text: str) -> Pattern:
        """From ``a-b,b-c``; separators may be commas or blanks."""
        found = cls.of(tuple(part.split("-")) for part in text.replace(",", " ").split())
        if not found.edges or not found.connected:
            raise ValueError("a pattern is connected and has an edge")
        return found

    @cached_property
    def vertices(self) -> tuple[str, ...]:
        return tuple(sorted({v for e in self.edges for v in e}))

    @cached_property
    def neighbours(self) -> dict[str, frozenset[str]]:
        return {v: frozenset(y if x == v else x for x, y in self.edges if v in (x, y)) for v in self.vertices}

    def degree(self, v: str) -> int:
        return len(self.neighbours[v])

    @cached_property
    def connected(self) -> bool:
        return reach(self.vertices, self.neighbours)

    def induced(self, kept) -> Pattern:
        return Pattern(tuple(e for e in self.edges if e[0] in kept and e[1] in kept))

    def has(self, x: str, y: str) -> bool:
        return tuple(sorted((x, y))) in self.edges

    def __str__(self) -> str:
        return ",".join(f"{x}-{y}" for x, y in self.edges)


def reach(vertices, neighbours) -> bool:
    """Whether the vertices are connected among themselves."""
    vertices = set(vertices)
    if not vertices:
        return True
    todo, seen = [next(iter(vertices))], set()
    while todo:
        v = todo.pop()
        if v not in seen:
            seen.add(v)
            todo += [w for w in neighbours[v] if w in vertices]
    return seen == vertices


# Stand-ins for the patterns of the experiments, and further ones.
PATTERNS = {
    "square": "a-b b-c c-d a-d",
    "triangle": "a-b b-c a-c",
    "house": "a-b b-c c-d a-d a-e b-e",
    "diamond": "a-b b-c c-d a-d a-c",
    "wheel4": "h-a h-b h-c h-d a-b b-c c-d a-d",
    "k4tri": "a-b a-c a-d b-c b-d c-d a-e b-e",
    "path3": "a-b b-c",
    "path4": "a-b b-c c-d",
    "star3": "h-a h-b h-c",
    "clique4": "a-b a-c a-d b-c b-d c-d",
    "clique5": "a-b a-c a-d a-e b-c b-d b-e c-d c-e d-e",
    "fan4": "h-a h-b h-c h-d a-b b-c c-d",
    "bowtie": "h-a h-b h-c h-d a-b c-d",
    "cycle5": "a-b b-c c-d d-e a-e",
    "cycle6": "a-b b-c c-d d-e e-f a-f",
    "two_triangles_bridge": "a-b a-c b-c c-d d-e d-f e-f",
}


def named(name: str) -> Pattern:
    return Pattern.parse(PATTERNS[name])


def automorphisms(p: Pattern, order: Order = frozenset()) -> list[dict[str, str]]:
    """Vertex maps onto itself; with an order, those that keep each pair in the order of the vertices' names."""
    rank = {v: k for k, v in enumerate(p.vertices)}
    edges, out = set(p.edges), []
    for image in permutations(p.vertices):
        f = dict(zip(p.vertices, image, strict=True))
        if all(tuple(sorted((f[x], f[y]))) in edges for x, y in p.edges) and all(rank[f[x]] < rank[f[y]] for x, y in order):
            out.append(f)
    return out


def isomorphic(p: Pattern, q: Pattern) -> bool:
    if (len(p.vertices), len(p.edges)) != (len(q.vertices), len(q.edges)):
        return False
    target = set(q.edges)
    return any(all(tuple(sorted((f[x], f[y]))) in target for x, y in p.edges) for image in permutations(q.vertices) for f in [dict(zip(p.vertices, image, strict=True))])


def symmetry_order(p: Pattern) -> Order:
    """Pairs that leave one map for each subgraph: fix a movable vertex as the least of its orbit, go on with its stabiliser."""
    group, out = automorphisms(p), set()
    for v in p.vertices:
        orbit = {f[v] for f in group}
        out |= {(v, w) for w in orbit if w != v}
        group = [f for f in group if f[v] == v]
    return frozenset(out)


def restrict(order: Order, vertices) -> Order:
    """The pairs of an order that a piece with these vertices inherits."""
    return frozenset((x, y) for x, y in order if x in vertices and y in vertices)


def vertex_covers(p: Pattern, connected: bool = True) -> list[frozenset[str]]:
    """All sets that touch every edge, the smallest first; the connected ones are connected in the pattern."""
    out = []
    for size in range(1, len(p.vertices) + 1):
        for chosen in combinations(p.vertices, size):
            if all(x in chosen or y in chosen for x, y in p.edges) and (not connected or reach(chosen, p.neighbours)):
                out.append(frozenset(chosen))
    return out


def anchors(p: Pattern, cover: frozenset[str] | None = None) -> list[str]:
    """Vertices next to all others (and in the cover)."""
    return [v for v in p.vertices if p.degree(v) == len(p.vertices) - 1 and (cover is None or v in cover)]


def pick_anchor(q: Pattern, cover: frozenset[str] | None = None, policy: str = "min_id", whole: Pattern | None = None, seed: int = 0) -> str:
    """One anchor: the first by name, the one of largest degree in the whole pattern, or a seeded random one."""
    found = anchors(q, cover)
    if not found:
        raise ValueError("not a hub unit of this cover")
    if policy == "random":
        import random

        return random.Random(seed).choice(found)
    return max(found, key=lambda v: (whole or q).degree(v)) if policy == "max_pattern_degree" else found[0]


def pieces(p: Pattern) -> Iterator[Pattern]:
    """All connected pieces, by number of edges."""
    for size in range(1, len(p.edges) + 1):
        for chosen in combinations(p.edges, size):
            q = Pattern(chosen)
            if q.connected:
                yield q


def is_star(q: Pattern) -> bool:
    return len(q.edges) == len(q.vertices) - 1 and bool(anchors(q))


def is_clique(q: Pattern) -> bool:
    n = len(q.vertices)
    return len(q.edges) == n * (n - 1) // 2


def units(p: Pattern, family: str = "hub", cover: frozenset[str] | None = None, max_clique: int = 99) -> list[Pattern]:
    """Pieces that a family of join units has.

    ``hub``: pieces with a vertex next to all others (in the cover); ``triangles`` and
    ``cliques``: those, and single edges only where no such unit holds the edge;
    ``stars``; ``stars+cliques``.
    """
    out = [q for q in pieces(p) if anchors(q, cover)]
    if family == "hub":
        return out
    small = lambda q: is_clique(q) and len(q.vertices) <= max_clique
    tests = {
        "stars": is_star,
        "stars+cliques": lambda q: is_star(q) or small(q),
        "triangles": lambda q: is_clique(q) and len(q.vertices) == 3,
        "cliques": lambda q: small(q) and len(q.vertices) >= 3,
    }
    found = [q for q in out if tests[family](q)]
    held = {e for q in found for e in q.edges}
    return found + [q for q in out if len(q.edges) == 1 and q.edges[0] not in held]


def is_decomposition(parts: list[Pattern], p: Pattern, cover: frozenset[str] | None = None) -> bool:
    """Whether the parts are hub units whose union is the pattern."""
    return {e for q in parts for e in q.edges} == set(p.edges) and all(anchors(q, cover) for q in parts)


def decompositions(p: Pattern, limit: int = 1000, cover: frozenset[str] | None = None) -> list[list[Pattern]]:
    """Irredundant sets of hub units whose union is the pattern, few units first, at most ``limit``."""
    own, out = units(p, cover=cover), []
    for size in range(1, len(p.edges) + 1):
        for chosen in combinations(own, size):
            if is_decomposition(list(chosen), p) and all(not is_decomposition([q for q in chosen if q is not x], p) for x in chosen):
                out.append(list(chosen))
                if len(out) >= limit:
                    return out
        if size >= 4 and out:
            break
    return out


def min_units(p: Pattern, cover: frozenset[str]) -> list[tuple[str, Pattern]]:
    """Fewest (anchor, maximal unit at it) that make up the pattern; a maximal unit is what the pattern has on a closed neighbourhood."""
    at = {v: p.induced(p.neighbours[v] | {v}) for v in sorted(cover)}
    for size in range(1, len(at) + 1):
        for chosen in combinations(at, size):
            if {e for v in chosen for e in at[v].edges} == set(p.edges):
                return [(v, at[v]) for v in chosen]
    raise ValueError("the set is not a vertex cover")


def left_deep_orders(parts: list[tuple[str, Pattern]], cover: frozenset[str]) -> list[list[int]]:
    """For each unit, an order that starts with it and shares a cover vertex at every step."""
    out = []
    for first in range(len(parts)):
        order, seen = [first], set(parts[first][1].vertices)
        while len(order) < len(parts):
            nxt = next((k for k in range(len(parts)) if k not in order and seen & cover & set(parts[k][1].vertices)), None)
            if nxt is None:
                raise ValueError("the cover is not connected")
            order.append(nxt)
            seen |= set(parts[nxt][1].vertices)
        out.append(order)
    return out
