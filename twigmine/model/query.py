"""Text form of patterns, queries with a head, and their SQL."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from .pattern import FREE, HIDDEN, PINNED, Pattern

TOKEN = re.compile(r"\s*([(),]|[#?]?[^\s(),#?=]*(?:=[^\s(),]+)?)")


@dataclass(frozen=True)
class Named:
    """A pattern with the names of its nodes and the constants of some pins (by position)."""

    pattern: Pattern
    names: tuple[str, ...]
    constants: dict[int, str] = field(default_factory=dict)

    def at(self, name: str) -> int:
        return self.names.index(name)

    def bind(self, **values) -> Named:
        """With constants for pins by name."""
        got = {self.at(k): v for k, v in values.items()}
        if any(self.pattern.marks[i] != PINNED for i in got):
            raise ValueError("constants go to pins only")
        return Named(self.pattern, self.names, {**self.constants, **got})

    def literal(self) -> Named:
        """Every pin's name taken as its constant."""
        return Named(self.pattern, self.names, {i: self.constants.get(i, self.names[i]) for i in self.pattern.pins})


def parse_pattern(text: str) -> Named:
    """x(?h(#a, y), #b=20): ? hidden, # pinned, =v a constant; a hidden node may go without a name."""
    levels, marks, names, constants = [], [], [], {}
    depth, at, expect = 0, 0, True
    text = text.strip()
    while at < len(text):
        m = TOKEN.match(text, at)
        token = m[1]
        if not token:
            raise ValueError(f"cannot read {text[at:]!r}")
        at = m.end()
        if token == "(":
            depth, expect = depth + 1, True
        elif token == ")":
            depth -= 1
        elif token == ",":
            expect = True
        else:
            if not expect or depth < 0 or (depth == 0 and levels):
                raise ValueError(f"a node is not expected at {token!r}")
            expect = False
            mark = {"?": HIDDEN, "#": PINNED}.get(token[0], FREE)
            name, _, value = token.lstrip("?#").partition("=")
            if mark == FREE and (not name or value) or mark == PINNED and not name:
                raise ValueError(f"a head or node needs no constant here: {token!r}")
            if value:
                constants[len(levels)] = value
            levels.append(depth)
            marks.append(mark)
            names.append(name or f"h{len(levels) - 1}")
    if depth or not levels:
        raise ValueError(f"brackets do not match in {text!r}")
    return Named(Pattern(tuple(levels), "".join(marks)), tuple(names), constants)


def show(p: Pattern, constants: dict | None = None) -> str:
    """Text form, nodes named by position."""
    kids = p.children

    def walk(v: int) -> str:
        name = {FREE: f"x{v}", HIDDEN: "?", PINNED: f"#c{v}"}[p.marks[v]]
        if constants and v in constants:
            name += f"={constants[v]}"
        return name + (f"({', '.join(map(walk, kids[v]))})" if kids[v] else "")

    return walk(0)


@dataclass(frozen=True)
class TreeQuery:
    """A body with a head: positions of free nodes and pins, repeats allowed, every free node in it, no hidden one."""

    head: tuple[int, ...]
    body: Pattern

    def __post_init__(self) -> None:
        if any(not 0 <= h < self.body.size for h in self.head):
            raise ValueError("the head names nodes of the body; constants are pins of the body")
        if any(self.body.marks[h] == HIDDEN for h in self.head):
            raise ValueError("a hidden node cannot stand in the head")
        if {*self.body.free} - {*self.head}:
            raise ValueError("every free node must stand in the head")

    def is_pure(self) -> bool:
        return self.head == self.body.free


def pure(p: Pattern) -> TreeQuery:
    """The query that asks for a pattern's answers."""
    return TreeQuery(p.free, p)


def purify(q: TreeQuery) -> TreeQuery:
    """Pins and repeats out of the head: the support stays as it is."""
    return pure(q.body)


def freeze(q: TreeQuery, prefix: str = "k") -> tuple[list[tuple[str, str]], tuple[str, ...], tuple[str, ...]]:
    """The body as a data graph of one fresh constant per node: edges, head tuple, constants of all nodes."""
    nodes = tuple(f"{prefix}{i}" for i in range(q.body.size))
    return [(nodes[p], nodes[i]) for i, p in enumerate(q.body.parent) if p >= 0], tuple(nodes[h] for h in q.head), nodes


def quoted(value) -> str:
    return str(value) if isinstance(value, (int, float)) else "'" + str(value).replace("'", "''") + "'"


def to_sql(p: Pattern, constants: dict | None = None, edges: str = "edge", nodes: str | None = None, minsup: int | None = None, dialect: str = "duckdb") -> str:
    """Support table of a pattern: pin1..pinK (pins without constants, in preorder) and freq.

    One copy of the edges for each tree edge; a child's copy begins where its parent's ends (at the root all begin together); what is
    not hidden is selected distinct and counted for each combination of the pins.
    """
    constants = constants or {}
    cast = "BIGINT"
    parent, kids = p.parent, p.children
    node = {0: f"e{kids[0][0]}.src"} if kids[0] else {0: "n.id"}
    node |= {i: f"e{i}.dst" for i in range(1, p.size)}
    where = [f"e{i}.src = {node[parent[i]]}" for i in range(1, p.size) if node[parent[i]] != f"e{i}.src"]
    where += [f"{node[i]} = {quoted(v)}" for i, v in constants.items()]
    source = ", ".join(f"{edges} e{i}" for i in range(1, p.size)) or (nodes or f"(SELECT src AS id FROM {edges} UNION SELECT dst FROM {edges})") + " n"
    visible = [i for i in range(p.size) if p.marks[i] != HIDDEN]
    columns = ", ".join(f"{node[i]} AS n{i}" for i in visible) or "1 AS one"
    inner = f"SELECT DISTINCT {columns} FROM {source}" + (" WHERE " + " AND ".join(where) if where else "")
    free_pins = [i for i in p.pins if i not in constants]
    names = "".join(f"n{i} AS pin{k}, " for k, i in enumerate(free_pins, 1))
    group = " GROUP BY " + ", ".join(f"n{i}" for i in free_pins) if free_pins else ""
    having = f" HAVING count(*) >= {minsup}" if minsup else ""
    return f"SELECT {names}CAST(count(*) AS {cast}) AS freq FROM ({inner}) q{group}{having}"
