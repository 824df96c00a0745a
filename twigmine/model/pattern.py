"""Patterns: a tree whose nodes are free (d), hidden (e) or pinned (p), and the tests that keep the search small."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import product

from .shape import Levels, children_of, height, parents_of, tree_key

FREE, HIDDEN, PINNED = "d", "e", "p"


@dataclass(frozen=True)
class Pattern:
    levels: Levels
    marks: str

    def __post_init__(self) -> None:
        if len(self.levels) != len(self.marks) or not self.levels or set(self.marks) - {FREE, HIDDEN, PINNED}:
            raise ValueError(f"not a pattern: {self.levels} {self.marks}")
        if self.levels[0] != 0 or any(not 1 <= b <= a + 1 for a, b in zip(self.levels, self.levels[1:], strict=False)):
            raise ValueError(f"not a tree: {self.levels}")

    @property
    def size(self) -> int:
        return len(self.levels)

    @property
    def height(self) -> int:
        return height(self.levels)

    @property
    def parent(self) -> tuple[int, ...]:
        return parents_of(self.levels)

    @property
    def children(self) -> list[list[int]]:
        return children_of(self.levels)

    def having(self, mark: str) -> tuple[int, ...]:
        return tuple(i for i, m in enumerate(self.marks) if m == mark)

    @property
    def free(self) -> tuple[int, ...]:
        return self.having(FREE)

    @property
    def hidden(self) -> tuple[int, ...]:
        return self.having(HIDDEN)

    @property
    def pins(self) -> tuple[int, ...]:
        return self.having(PINNED)

    @property
    def level(self) -> int:
        """Number of hidden and pinned nodes: the level at which the search meets the pattern."""
        return self.size - len(self.free)

    @property
    def tree_key(self) -> str:
        return tree_key(self.levels)

    def marked(self, node: int, mark: str) -> Pattern:
        return Pattern(self.levels, self.marks[:node] + mark + self.marks[node + 1 :])

    def parents(self) -> list[Pattern]:
        """One hidden node or one pin made free again."""
        return [self.marked(i, FREE) for i, m in enumerate(self.marks) if m != FREE]

    def extensions(self) -> list[Pattern]:
        """One free node made hidden or pinned."""
        return [self.marked(i, m) for i in self.free for m in (HIDDEN, PINNED)]

    def refined(self) -> str:
        """Depth and mark of every node in this order."""
        return "".join(f"{level}{mark}" for level, mark in zip(self.levels, self.marks, strict=True))

    def canonize(self) -> tuple[Pattern, tuple[int, ...]]:
        """The canonical order of this pattern, and the old position of each of its nodes.

        Children stand by falling unmarked sequence, then by falling marks (p over e over d), so the node positions of a canonical
        shape are kept.
        """
        kids = self.children

        def walk(v: int, depth: int) -> tuple[Levels, str, tuple[int, ...]]:
            parts = sorted((walk(c, depth + 1) for c in kids[v]), key=lambda x: (x[0], x[1]), reverse=True)
            return (depth, *(y for x in parts for y in x[0])), self.marks[v] + "".join(x[1] for x in parts), (v, *(y for x in parts for y in x[2]))

        levels, marks, old = walk(0, 0)
        return Pattern(levels, marks), old

    def is_canonical(self) -> bool:
        return self.canonize()[0] == self

    def chains(self) -> dict[int, int]:
        """Nodes whose subtree is a path of hidden nodes, and the path's length in nodes."""
        kids, out = self.children, {}
        for v in range(self.size - 1, -1, -1):
            if self.marks[v] == HIDDEN and (not kids[v] or len(kids[v]) == 1 and kids[v][0] in out):
                out[v] = 1 + (out[kids[v][0]] if kids[v] else 0)
        return out

    def depths(self) -> list[int]:
        """Nodes on the longest path down from each node."""
        kids, out = self.children, [1] * self.size
        for v in range(self.size - 1, -1, -1):
            out[v] = 1 + max((out[c] for c in kids[v]), default=0)
        return out

    def redundant_chains(self) -> list[int]:
        """Tops of hidden paths that a sibling subtree at least as deep makes needless."""
        parent, kids, depth = self.parent, self.children, self.depths()
        return [v for v, n in self.chains().items() if v and any(c != v and depth[c] >= n for c in kids[parent[v]])]

    def has_redundancy(self) -> bool:
        return bool(self.redundant_chains())

    def becomes_redundant(self, node: int) -> bool:
        """Whether hiding node makes a pattern without redundancy redundant: only the path that node joins is looked at, and its top's siblings."""
        hidden = self.marked(node, HIDDEN)
        parent, kids, depth, chains = hidden.parent, hidden.children, hidden.depths(), hidden.chains()
        top = node
        while top in chains:
            if top and any(c != top and depth[c] >= chains[top] for c in kids[parent[top]]):
                return True
            if not top:
                break
            top = parent[top]
        return False

    def without(self, top: int) -> tuple[Pattern, tuple[int, ...]]:
        """The pattern without the subtree at top, and the old positions of what stays."""
        end = top + 1
        while end < self.size and self.levels[end] > self.levels[top]:
            end += 1
        keep = (*range(top), *range(end, self.size))
        return Pattern(tuple(self.levels[i] for i in keep), "".join(self.marks[i] for i in keep)), keep

    def reduce(self) -> tuple[Pattern, tuple[int, ...]]:
        """An equivalent pattern without redundancy, and the old positions of its nodes."""
        p, old = self, tuple(range(self.size))
        while chains := p.redundant_chains():
            p, keep = p.without(max(chains))
            old = tuple(old[i] for i in keep)
        return p, old

    def normal(self) -> tuple[Pattern, tuple[int, ...]]:
        """Reduced and canonical, with the old positions."""
        p, old = self.reduce()
        c, order = p.canonize()
        return c, tuple(old[i] for i in order)


def pattern_key(p: Pattern) -> str:
    """Equal for isomorphic patterns only: the canonical refined sequence."""
    return p.canonize()[0].refined()


def pattern_of_key(key: str) -> Pattern:
    parts = re.findall(r"(\d+)([dep])", key)
    return Pattern(tuple(int(a) for a, _ in parts), "".join(b for _, b in parts))


def isomorphic(a: Pattern, b: Pattern) -> bool:
    return pattern_key(a) == pattern_key(b)


def specializes(a: Pattern, b: Pattern, alpha: dict | None = None, beta: dict | None = None) -> bool:
    """a hides and pins at least what b does, on one tree, with b's constants."""
    alpha, beta = alpha or {}, beta or {}
    return a.levels == b.levels and {*a.hidden} >= {*b.hidden} and {*a.pins} >= {*b.pins} and all(alpha.get(i) == v for i, v in beta.items())


def all_marks(levels: Levels, dedup: str = "full") -> Iterator[Pattern]:
    """Patterns over a tree: all markings ('none'), one of each isomorphism class ('canonical'), those without redundancy, or both ('full')."""
    for marks in product("dep", repeat=len(levels)):
        p = Pattern(levels, "".join(marks))
        if dedup in ("canonical", "full") and not p.is_canonical() or dedup in ("redundancy", "full") and p.has_redundancy():
            continue
        yield p
