"""Fold maps (containment mappings) between patterns and queries, and what follows from them."""

from __future__ import annotations

from collections.abc import Iterator

from .pattern import FREE, HIDDEN, PINNED, Pattern
from .query import TreeQuery

Fold = tuple[int, ...]


def fits(a: str, b: str) -> bool:
    """Whether a node marked a may land on one marked b: pins on pins, free ones on free ones or pins, hidden ones anywhere."""
    return a == HIDDEN or b == PINNED or a == FREE and b == FREE


def is_fold(f: Fold, p1: Pattern, p2: Pattern, rho: dict[int, int] | None = None) -> bool:
    parent1, parent2 = p1.parent, p2.parent
    edges = all(p < 0 or parent2[f[i]] == f[p] for i, p in enumerate(parent1))
    return edges and all(fits(p1.marks[i], p2.marks[f[i]]) for i in range(p1.size)) and all(f[i] == j for i, j in (rho or {}).items())


def is_query_fold(f: Fold, q1: TreeQuery, q2: TreeQuery, rho: dict[int, int] | None = None) -> bool:
    return is_fold(f, q1.body, q2.body, rho) and tuple(f[h] for h in q1.head) == q2.head


def compose(second: Fold, first: Fold) -> Fold:
    return tuple(second[i] for i in first)


def match_matrix(p1: Pattern, p2: Pattern) -> list[list[bool]]:
    """m[i][j]: the subtree at i can be folded with i on j.  Filled from the leaves of both trees up."""
    k1, k2 = p1.children, p2.children
    m = [[False] * p2.size for _ in range(p1.size)]
    for i in range(p1.size - 1, -1, -1):
        for j in range(p2.size):
            m[i][j] = fits(p1.marks[i], p2.marks[j]) and all(any(m[c][d] for d in k2[j]) for c in k1[i])
    return m


def fold_maps(p1: Pattern, p2: Pattern) -> Iterator[Fold]:
    """All fold maps, one at a time: nodes are placed in preorder, and every choice is one that the matrix says can be finished.

    So no branch is dead, the next map is never further away than both patterns' sizes multiplied, and only one map is held.
    """
    m, parent, k2 = match_matrix(p1, p2), p1.parent, p2.children
    f = [0] * p1.size

    def place(i: int) -> Iterator[Fold]:
        if i == p1.size:
            yield tuple(f)
            return
        for j in k2[f[parent[i]]] if i else range(p2.size):
            if m[i][j]:
                f[i] = j
                yield from place(i + 1)

    yield from place(0)


def covers_free(f: Fold, p2: Pattern, p1: Pattern | None = None) -> bool:
    """Whether the image of what may stand in a head holds every free node of p2."""
    image = {f[i] for i in range(len(f)) if p1 is None or p1.marks[i] != HIDDEN}
    return {*p2.free} <= image


def contains(q1: TreeQuery, q2: TreeQuery, rho: dict[int, int]) -> bool:
    """q2's answers are among q1's whenever q1's pins take the constants of their images: there is a fold from q1 to q2."""
    return any(is_query_fold(f, q1, q2, rho) for f in fold_maps(q1.body, q2.body))


def correspondences(p1: Pattern, p2: Pattern) -> set[tuple[tuple[tuple[int, int], ...], tuple[tuple[int, int], ...]]]:
    """(delta, rho) of the folds that map free nodes to free nodes and pins to pins one to one and onto."""
    out = set()
    for f in fold_maps(p1, p2):
        delta, rho = tuple((i, f[i]) for i in p1.free), tuple((i, f[i]) for i in p1.pins)
        if sorted(j for _, j in delta) == list(p2.free) and sorted(j for _, j in rho) == list(p2.pins):
            out.add((delta, rho))
    return out


def equivalent(p1: Pattern, p2: Pattern) -> list[tuple[dict[int, int], dict[int, int]]]:
    """Every pair of one-to-one correspondences of free nodes and of pins under which the patterns have the same answers."""
    back = correspondences(p2, p1)
    turn = lambda pairs: tuple(sorted((b, a) for a, b in pairs))
    return [(dict(d), dict(r)) for d, r in sorted(correspondences(p1, p2)) if (turn(d), turn(r)) in back]
