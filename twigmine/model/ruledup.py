"""Equivalent rules: fold maps that differ only by symmetries of the two patterns."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from itertools import permutations, product
from math import factorial, prod

from .contain import Fold
from .pattern import FREE, HIDDEN, Pattern


def automorphisms(p: Pattern) -> Iterator[tuple[int, ...]]:
    """All mark-preserving symmetries, each as the image of every node."""
    kids = p.children

    def key(v: int) -> tuple:
        return (p.marks[v], tuple(sorted(key(c) for c in kids[v])))

    def onto(a: int, b: int) -> Iterator[dict[int, int]]:
        """Isomorphisms of the subtree at a onto the one at b."""
        if key(a) != key(b):
            return
        groups: dict[tuple, tuple[list[int], list[int]]] = {}
        for side, v in ((0, a), (1, b)):
            for c in kids[v]:
                groups.setdefault(key(c), ([], []))[side].append(c)
        per_group = []
        for left, right in groups.values():
            options = []
            for image in permutations(right):
                options += [merge(x) for x in product(*(list(onto(s, t)) for s, t in zip(left, image, strict=True)))]
            per_group.append(options)
        for choice in product(*per_group):
            yield {a: b} | merge(choice)

    def merge(parts: Iterable[dict[int, int]]) -> dict[int, int]:
        out: dict[int, int] = {}
        for x in parts:
            out |= x
        return out

    for image in onto(0, 0):
        yield tuple(image[i] for i in range(p.size))


def symmetry_count(p: Pattern) -> int:
    """Number of automorphisms, without listing them."""
    kids = p.children
    keys: list = [None] * p.size
    counts = [1] * p.size
    for v in range(p.size - 1, -1, -1):
        keys[v] = (p.marks[v], tuple(sorted(keys[c] for c in kids[v])))
        counts[v] = prod(counts[c] for c in kids[v]) * prod(factorial(n) for n in Counter(keys[c] for c in kids[v]).values())
    return counts[0]


def fold_key(f: Fold, lhs: Pattern, rhs: Pattern) -> str:
    """Canonical form of rhs with each node labelled by its mark and the lhs nodes on it; lhs stands still.  Linear in the sizes."""
    on: dict[int, list[int]] = {}
    for i, j in enumerate(f):
        on.setdefault(j, []).append(i)
    kids = rhs.children

    def walk(v: int) -> str:
        return f"{rhs.marks[v]}{','.join(map(str, on.get(v, [])))}({''.join(sorted(map(walk, kids[v])))})"

    return walk(0)


def fold_key_full(f: Fold, lhs: Pattern, rhs: Pattern) -> str:
    """The least fold_key over all symmetries of lhs: equal for equivalent folds only."""
    return min(fold_key(tuple(f[g[i]] for i in range(lhs.size)), lhs, rhs) for g in automorphisms(lhs))


@dataclass(frozen=True)
class ColoredGraph:
    """Vertices by color, edges (u, v, color) directed."""

    colors: tuple[int, ...]
    edges: frozenset[tuple[int, int, int]]


def fold_graph(f: Fold, lhs: Pattern, rhs: Pattern) -> ColoredGraph:
    """Both trees and the map in one graph: three colors of vertices (marks) and of edges (lhs, rhs, map)."""
    color = {FREE: 0, HIDDEN: 1}
    n = lhs.size
    edges = {(p, i, 0) for i, p in enumerate(lhs.parent) if p >= 0} | {(n + p, n + i, 1) for i, p in enumerate(rhs.parent) if p >= 0}
    return ColoredGraph(tuple(color.get(m, 2) for m in lhs.marks + rhs.marks), frozenset(edges | {(i, n + j, 2) for i, j in enumerate(f)}))


def colored_isomorphic(a: ColoredGraph, b: ColoredGraph) -> bool:
    """Exact test: colors are refined together by neighbourhoods until they settle, then a vertex of the smallest class that is left is tried on each of its images."""
    if len(a.colors) != len(b.colors) or len(a.edges) != len(b.edges):
        return False
    n = len(a.colors)
    around = []
    for g in (a, b):
        near: list[list[tuple[int, int, int]]] = [[] for _ in range(n)]
        for u, v, c in g.edges:
            near[u].append((0, c, v))
            near[v].append((1, c, u))
        around.append(near)

    def settle(x: list[int], y: list[int]) -> tuple[list[int], list[int]] | None:
        while True:
            names: dict[tuple, int] = {}
            new = []
            for side, colors in enumerate((x, y)):
                new.append([names.setdefault((colors[v], tuple(sorted((d, c, colors[u]) for d, c, u in around[side][v]))), len(names)) for v in range(n)])
            if Counter(new[0]) != Counter(new[1]):
                return None
            if len(set(new[0])) == len(set(x)):
                return new[0], new[1]
            x, y = new

    def search(x: list[int], y: list[int]) -> bool:
        settled = settle(x, y)
        if settled is None:
            return False
        x, y = settled
        classes = Counter(x)
        open_classes = [(k, c) for c, k in classes.items() if k > 1]
        if not open_classes:
            to = {c: v for v, c in enumerate(y)}
            image = [to[c] for c in x]
            return {(image[u], image[v], c) for u, v, c in a.edges} == b.edges
        _, c = min(open_classes)
        v = x.index(c)
        for w in (w for w in range(n) if y[w] == c):
            x2, y2 = list(x), list(y)
            x2[v] = y2[w] = n + 1 + c
            if search(x2, y2):
                return True
        return False

    return search(list(a.colors), list(b.colors))


def equivalent_folds(f1: Fold, f2: Fold, lhs: Pattern, rhs: Pattern) -> bool:
    """Whether symmetries g of lhs and h of rhs exist with f2 after g equal to h after f1.

    With few symmetries of lhs their least key decides; with many the colored graphs are compared."""
    if symmetry_count(lhs) <= 10_000:
        return fold_key_full(f1, lhs, rhs) == fold_key_full(f2, lhs, rhs)
    return colored_isomorphic(fold_graph(f1, lhs, rhs), fold_graph(f2, lhs, rhs))


def distinct_folds(folds: Iterable[Fold], lhs: Pattern, rhs: Pattern, dedup: str = "linear") -> list[Fold]:
    """The folds without repeats: 'none' keeps all, 'linear' compares with lhs held still, 'complete' with all its symmetries."""
    if dedup == "none":
        return list(folds)
    seen: dict[str, Fold] = {}
    for f in folds:
        seen.setdefault(fold_key(f, lhs, rhs), f)
    out: list[Fold] = []
    for f in seen.values():
        if dedup != "complete" or not any(equivalent_folds(f, g, lhs, rhs) for g in out):
            out.append(f)
    return out


def bipartite_to_folds(n_left: int, n_right: int, edges: Iterable[tuple[int, int]]) -> tuple[Pattern, Pattern, Fold]:
    """A bipartite graph as a fold: two graphs give equivalent folds on one (lhs, rhs) just if they are isomorphic side by side.

    lhs has a branch for each left vertex with a leaf for each of its edges, rhs one branch with a leaf for each right vertex, and a
    leaf goes to its edge's right end.  Left vertices stand by falling degree, so isomorphic graphs get one lhs.
    """
    beside: dict[int, list[int]] = {i: [] for i in range(n_left)}
    for a, b in edges:
        beside[a].append(b)
    levels, f = [0], [0]
    for a in sorted(beside, key=lambda i: -len(beside[i])):
        levels.append(1)
        f.append(1)
        for b in beside[a]:
            levels.append(2)
            f.append(2 + b)
    rhs = Pattern((0, 1, *[2] * n_right), FREE * (n_right + 2))
    return Pattern(tuple(levels), FREE * len(levels)), rhs, tuple(f)


def digraph_to_bipartite(edges: Iterable[tuple[int, int]]) -> list[tuple[tuple[str, int], tuple[str, int]]]:
    """A digraph's incidence: each edge becomes two vertices in a row between its ends, told apart by their side."""
    out = []
    for k, (u, v) in enumerate(edges):
        out += [(("node", u), ("edge", 2 * k)), (("node", v), ("edge", 2 * k)), (("node", v), ("edge", 2 * k + 1))]
    return out
