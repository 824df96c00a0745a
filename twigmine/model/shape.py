"""Rooted unordered trees as level sequences: the depth of every node in preorder, largest sequence of all child orders first."""

from __future__ import annotations

from collections.abc import Iterator

Levels = tuple[int, ...]


def parents_of(levels: Levels) -> tuple[int, ...]:
    """Position of each node's parent (-1 for the root)."""
    last: dict[int, int] = {}
    out = []
    for i, level in enumerate(levels):
        out.append(last.get(level - 1, -1))
        last[level] = i
    return tuple(out)


def children_of(levels: Levels) -> list[list[int]]:
    kids: list[list[int]] = [[] for _ in levels]
    for i, p in enumerate(parents_of(levels)):
        if p >= 0:
            kids[p].append(i)
    return kids


def height(levels: Levels) -> int:
    """Edges on the longest path from the root."""
    return max(levels) - levels[0]


def canonical_shape(levels: Levels) -> Levels:
    kids = children_of(levels)

    def walk(v: int, depth: int) -> Levels:
        subtrees = sorted((walk(c, depth + 1) for c in kids[v]), reverse=True)
        return (depth, *(x for s in subtrees for x in s))

    return walk(0, 0)


def next_shape(levels: Levels) -> Levels | None:
    """The next smaller canonical sequence of as many nodes: the last node below depth one goes up to stand beside its parent, and what follows repeats the branch it left."""
    last = max((i for i, depth in enumerate(levels) if depth > 1), default=None)
    if last is None:
        return None
    above = max(i for i in range(last) if levels[i] == levels[last] - 1)
    out = list(levels[:last])
    while len(out) < len(levels):
        out.append(out[len(out) - (last - above)])
    return tuple(out)


def shapes(max_nodes: int | None = None, min_height: int = 0) -> Iterator[Levels]:
    """Every unordered rooted tree once, by growing size, the path first; without max_nodes it goes on until the caller stops.  Only the last tree is held."""
    n = 1
    while max_nodes is None or n <= max_nodes:
        tree: Levels | None = tuple(range(n))
        while tree is not None:
            if height(tree) >= min_height:
                yield tree
            tree = next_shape(tree)
        n += 1


def tree_key(levels: Levels) -> str:
    return "-".join(map(str, levels))


def shape_of_key(key: str) -> Levels:
    return tuple(map(int, key.split("-")))
