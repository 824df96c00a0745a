"""Support tables of patterns, in four ways with one answer.

expand  joins all tree edges, keeps what is not hidden, distinct, and counts.  It makes one row per match.
fold    works from the leaves up and carries counts instead of rows: given the value of a visible node, what hangs below it is
        independent of the rest, so only (value, pins below, count) goes up, and counts multiply.  Only inside a region of hidden
        nodes are edges joined, and there distinct removes the hidden values before anything is counted.
cube    counts all choices of pins of one hidden set in a single grouping-sets query over the distinct visible rows.
probe   starts from candidate pin values and walks outwards.
blocks  counts x(#a, #b) alone, by blocks of children (pairs.py): no row per pair of children.

Columns are n<i> for node i.  Sums are BIGINT in ANSI mode: an overflow is an error, never a wrong count.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph
from ..model.pattern import FREE, HIDDEN, PINNED, Pattern
from .pairs import common_parents

STRATEGIES = ("expand", "fold", "probe")
#: Two branches with pins meet at a node of a wide graph in this many times this many cells.
SPREAD = 4


def n(i: int) -> str:
    return f"n{i}"


class Edges:
    """Edge scans for the nodes of a pattern: constants and allowed values go into the scan.

    allowed: tables of values n<i> for sets of pins (a lone pin may stand for its set).  Rows are held against a table as soon as they have its pins,
    and before against the values of the pins that they have, where no smaller table has just these.
    """

    def __init__(self, g: Graph, constants: dict | None = None, allowed: dict | None = None):
        self.g, self.constants = g, constants or {}
        self.lone: dict[int, bool] = {}
        self.allowed = {(k,) if isinstance(k, int) else tuple(k): t.toDF(*[n(i) for i in ((k,) if isinstance(k, int) else k)]) for k, t in (allowed or {}).items()}

    def where_lone(self, child: int, lone: bool) -> Edges:
        """The same, but the child's values are those with one parent, or those with several (wide graphs)."""
        out = Edges(self.g, self.constants)
        out.allowed, out.lone = self.allowed, self.lone | {child: lone}
        return out

    def restrict(self, df: DataFrame, *nodes: int) -> DataFrame:
        for i in nodes:
            if i in self.constants:
                df = df.filter(F.col(n(i)) == F.lit(self.constants[i]))
        return self.meet(df, nodes)

    def meet(self, df: DataFrame, pins, *before) -> DataFrame:
        """Rows with these pins whose values every table allows; before: sets of pins that have been held against the tables."""
        done = set()
        for k, t in sorted(self.allowed.items(), key=lambda x: (len(x[0]), x[0])):
            have = tuple(i for i in k if i in pins and i not in self.constants)
            if not have or have in done or any({*have} <= {*b} for b in before):
                continue
            done.add(have)
            names = [n(i) for i in have]
            df = df.join(t.select(*names).distinct() if len(have) < len(k) else t, names, "left_semi")
        return df

    def edge(self, parent: int, child: int) -> DataFrame:
        edges = self.g.edges
        if child in self.lone:
            edges = edges.filter("lone" if self.lone[child] else "not lone")
        return self.restrict(edges.select(F.col("src").alias(n(parent)), F.col("dst").alias(n(child))), parent, child)

    def node(self, i: int) -> DataFrame:
        return self.restrict(self.g.nodes.select(F.col("id").alias(n(i))), i)


def matchings(g: Graph, p: Pattern, constants: dict | None = None) -> DataFrame:
    """One row per homomorphism, a column for every node."""
    edges = Edges(g, constants)
    if p.size == 1:
        return edges.node(0)
    df = None
    for i in range(1, p.size):
        e = edges.edge(p.parent[i], i)
        df = e if df is None else df.join(e, n(p.parent[i]))
    return df.select(*[n(i) for i in range(p.size)])


def visible_rows(g: Graph, p: Pattern, constants: dict | None = None, allowed: dict | None = None, start: DataFrame | None = None) -> DataFrame:
    """Distinct values of the free and pinned nodes over all matches.

    A hidden node's column goes as soon as its children are joined.  Hidden subtrees without visible nodes only filter.
    With start (rows of pin values) the join begins there and follows the tree outwards.
    """
    edges = Edges(g, constants, allowed)
    visible = [i for i in range(p.size) if p.marks[i] != HIDDEN]
    if p.size == 1:
        df = edges.node(0)
        if start is not None:
            df = df.join(start, n(0), "left_semi")
        return df.distinct() if visible else df.agg(F.count(F.lit(1)).alias("c")).filter("c > 0").select(F.lit(1).alias("one"))
    parent, kids = p.parent, p.children
    todo = list(range(1, p.size))
    df, bound = (start, {i for i in p.pins if n(i) in start.columns}) if start is not None else (None, set())
    left = {i: len(kids[i]) + (parent[i] >= 0) for i in range(p.size)}
    while todo:
        i = next((x for x in todo if parent[x] in bound or x in bound), todo[0])
        todo.remove(i)
        e = edges.edge(parent[i], i)
        on = [n(x) for x in (parent[i], i) if x in bound]
        df = e if df is None else df.join(e, on)
        bound |= {parent[i], i}
        for x in (parent[i], i):
            left[x] -= 1
        gone = [n(x) for x in bound if p.marks[x] == HIDDEN and left[x] == 0 and n(x) in df.columns]
        if gone:
            df = df.drop(*gone).distinct() if len(df.columns) > len(gone) else df.select(F.lit(1).alias("one")).distinct()
    return df.select(*[n(i) for i in visible] or ["one"]).distinct()


def _product(names: list[str]):
    return reduce(lambda a, b: a * b, [F.col(c) for c in names]) if names else F.lit(1).cast("bigint")


def _spread(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Their join on the key, dealt to cells by the rest of both sides' rows, so that a key with many rows on both is no single task's."""
    every = F.explode(F.sequence(F.lit(0), F.lit(SPREAD - 1)))
    own = lambda df: F.pmod(F.xxhash64(*[c for c in df.columns if c != key]), F.lit(SPREAD)).cast("int")
    return a.withColumn("_a", own(a)).withColumn("_b", every).join(b.withColumn("_b", own(b)).withColumn("_a", every), [key, "_a", "_b"]).drop("_a", "_b")


class _Fold:
    """The fold strategy for one pattern.

    In wide graphs, least (above 1) is a support below which assignments may go before the branches at the top node meet; settled: the pins settle the
    value of the root, which makes one row for each of their assignments.
    """

    def __init__(self, p: Pattern, edges: Edges, least: int = 1, settled: bool = False):
        self.p, self.edges, self.kids, self.least, self.settled = p, edges, p.children, least, settled

    def pins_below(self, v: int) -> list[int]:
        own = [v] if self.p.marks[v] == PINNED else []
        return own + [x for c in self.kids[v] for x in self.pins_below(c)]

    def at(self, v: int, top: bool = False, above: DataFrame | None = None) -> DataFrame | None:
        """For a visible node: its value, the pins strictly below, and cnt, the number of free assignments strictly below; None if nothing is below.

        top: all pins are at or below v, and above counts the free assignments elsewhere."""
        below = [self.pins_below(c) for c in self.kids[v]]
        parts = [self.seen_from(v, c).withColumnRenamed("cnt", f"cnt{k}") for k, c in enumerate(self.kids[v])]
        wide = top and self.edges.g.wide and sum(map(bool, below)) > 1
        if wide and self.least > 1:
            parts = self.bounded(v, parts, below, above)
        df, pinned = None, False
        # Branches without pins first: a row for each value of v at most.
        for k in sorted(range(len(parts)), key=lambda k: bool(below[k])):
            df = (self.reached(v, parts[k]) if len(parts) > 1 else parts[k]) if df is None else _spread(df, parts[k], n(v)) if wide and pinned else df.join(parts[k], n(v))
            pinned = bool(below[k])
        if df is None:
            return None
        counts = [f"cnt{k}" for k in range(len(self.kids[v]))]
        own = [v] if self.p.marks[v] == PINNED else []
        if len(below) > 1:
            df = self.edges.meet(df, own + sum(below, []), *[own + b for b in below])
        return df.select(n(v), *[n(x) for b in below for x in b], _product(counts).alias("cnt"))

    def reached(self, v: int, df: DataFrame) -> DataFrame:
        """In wide graphs, the rows whose value of v has a parent: the others would pair their children for nothing."""
        if not self.edges.g.wide or self.p.parent[v] < 0:
            return df
        return df.join(self.edges.edge(self.p.parent[v], v).select(n(v)).distinct(), n(v), "left_semi")

    def bounded(self, v: int, parts: list[DataFrame], below: list[list[int]], above: DataFrame | None) -> list[DataFrame]:
        """The branches without the assignments of their pins that can't reach the least support, whatever the other branches' pins are.

        At one value of v another branch gives the most that any of its assignments has there; over all values these add up."""
        single = self.settled or self.p.marks[v] == PINNED
        most = [part.groupBy(n(v)).agg(F.max(f"cnt{k}").alias(f"most{k}")) if below[k] else part.withColumnRenamed(f"cnt{k}", f"most{k}") for k, part in enumerate(parts)]
        out = []
        for k, part in enumerate(parts):
            if below[k]:
                pins, df, counts = [n(x) for x in below[k]], part, [f"cnt{k}"]
                for j, m in enumerate(most):
                    if j != k:
                        df, counts = df.join(m, n(v)), [*counts, f"most{j}"]
                if above is not None:
                    df, counts = df.join(above, n(v)), [*counts, "w"]
                if single:
                    part = df.filter(_product(counts) >= self.least).select(*part.columns)
                else:
                    part = part.join(df.groupBy(*pins).agg(F.sum(_product(counts)).alias("bound")).filter(F.col("bound") >= self.least), pins, "left_semi")
            out.append(part)
        return out

    def seen_from(self, v: int, c: int) -> DataFrame:
        """The branch c as its visible parent v sees it: value of v, pins in the branch, cnt of free assignments in the branch."""
        if self.p.marks[c] == HIDDEN:
            rows, ends = self.region(v, c)
            return self.counted(rows, ends, [n(v)])
        below, e = self.at(c), self.edges.edge(v, c)
        pins = [n(x) for x in self.pins_below(c)]
        if below is None:
            if self.p.marks[c] == PINNED:
                return e.withColumn("cnt", F.lit(1).cast("bigint"))
            return e.groupBy(n(v)).agg(F.count(F.lit(1)).alias("cnt"))
        joined = e.join(below, n(c))
        return joined.select(n(v), *pins, "cnt") if self.p.marks[c] == PINNED else joined.groupBy(n(v), *pins).agg(F.sum("cnt").alias("cnt"))

    def region(self, v: int | None, h: int) -> tuple[DataFrame, list[int]]:
        """The hidden region that begins at h below v: distinct values of v and of the visible nodes at its ends, and those nodes."""
        rows, ends = None, []
        for c in self.kids[h]:
            if self.p.marks[c] == HIDDEN:
                part, more = self.region(h, c)
            else:
                part, more = self.edges.edge(h, c), [c]
            ends += more
            part = self.reached(h, part) if rows is None and len(self.kids[h]) > 1 else part
            rows = part if rows is None else rows.join(part, n(h)) if more else rows.join(part, n(h), "left_semi")
        if v is None:
            if rows is None:
                rows = self.edges.node(h)
            return (rows.select(*[n(x) for x in ends]).distinct() if ends else rows.select(F.lit(1).alias("one")).limit(1)), ends
        e = self.edges.edge(v, h)
        if rows is not None:
            e = e.join(rows, n(h)) if ends else e.join(rows, n(h), "left_semi")
        return e.select(n(v), *[n(x) for x in ends]).distinct(), ends

    def counted(self, rows: DataFrame, ends: list[int], keys: list[str]) -> DataFrame:
        """Counts at a region's ends brought together for each key and pins."""
        counts = []
        for x in ends:
            below = self.at(x)
            if below is not None:
                rows = rows.join(below.withColumnRenamed("cnt", f"cnt_{x}"), n(x))
                counts.append(f"cnt_{x}")
        pins = [n(y) for x in ends for y in self.pins_below(x)]
        one = _product(counts)
        if not any(self.p.marks[x] == FREE for x in ends):
            return rows.select(*keys, *pins, one.alias("cnt"))
        return rows.groupBy(*keys, *pins).agg(F.sum(one).alias("cnt"))

    def from_above(self) -> tuple[int, DataFrame | None]:
        """The lowest visible node with all pins at or below it, and how many free assignments lie outside its branch: its value, w (None at the root).

        Counted down from the root, so no row is made for a pin and a free node above it.
        """
        v, above = 0, None
        while self.p.marks[v] == FREE:
            pinned = [c for c in self.kids[v] if self.pins_below(c)]
            if len(pinned) != 1 or self.p.marks[pinned[0]] == HIDDEN:
                break
            df, counts = self.edges.edge(v, pinned[0]), []
            if above is not None:
                df, counts = df.join(above, n(v)), ["w"]
            for c in self.kids[v]:
                if c != pinned[0]:
                    df = df.join(self.seen_from(v, c).withColumnRenamed("cnt", f"cnt{c}"), n(v))
                    counts.append(f"cnt{c}")
            v, above = pinned[0], df.groupBy(n(pinned[0])).agg(F.sum(_product(counts)).alias("w"))
        return v, above

    def table(self) -> DataFrame:
        p = self.p
        pins = [n(x) for x in p.pins]
        if p.marks[0] == HIDDEN:
            rows, ends = self.region(None, 0)
            if not ends:
                return rows.groupBy().agg(F.count(F.lit(1)).alias("freq")).filter("freq > 0")
            out = self.counted(rows, ends, [])
        else:
            top, above = self.from_above()
            out = self.at(top, True, above)
            if out is None:
                out = self.edges.node(0).withColumn("cnt", F.lit(1).cast("bigint")) if above is None else above.withColumnRenamed("w", "cnt")
            elif above is not None:
                out = out.join(above, n(top)).withColumn("cnt", F.col("cnt") * F.col("w"))
            if p.marks[top] == PINNED or self.settled:
                return out.select(*pins, F.col("cnt").alias("freq"))
        return out.groupBy(*pins).agg(F.coalesce(F.sum("cnt"), F.lit(0)).cast("bigint").alias("freq")).filter("freq > 0")


def _folded(p: Pattern, edges: Edges, minsup: int) -> DataFrame:
    """Pins and freq by the fold strategy, where freq may fall short of minsup.

    In a wide graph, a hidden root of two branches would pair all values that share a parent, and a free one below which pins come together would
    gather their pairs.  A child's value with one parent settles the root: those are counted apart, with a free root and, if the child is a pin, pair by
    pair without gathering.  Values with several parents go the plain way.
    """
    kids, pins = p.children[0], [n(i) for i in p.pins]
    fold = _Fold(p, edges, minsup)
    seen = [c for c in kids if p.marks[c] == PINNED] + ([c for c in kids if p.marks[c] == FREE] if p.marks[0] == HIDDEN else [])
    seen = [c for c in seen if c not in edges.lone]
    apart = edges.g.wide and seen and len(kids) > 1 and (p.marks[0] == HIDDEN or p.marks[0] == FREE and sum(bool(fold.pins_below(c)) for c in kids) > 1)
    if not apart:
        return fold.table()
    c = seen[0]
    pinned = p.marks[c] == PINNED
    # The two parts of a free child's values add up, so neither may be held against minsup alone.
    least = minsup if pinned else 1
    one = _Fold(Pattern(p.levels, FREE + p.marks[1:]), edges.where_lone(c, True), least, settled=pinned).table()
    both = one.select(*pins, "freq").union(_folded(p, edges.where_lone(c, False), least).select(*pins, "freq"))
    return both if pinned else both.groupBy(*pins).agg(F.sum("freq").alias("freq")).filter("freq > 0")


def support_table(g: Graph, p: Pattern, constants: dict | None = None, minsup: int = 1, strategy: str = "fold", allowed: dict | None = None, candidates: DataFrame | None = None) -> DataFrame:
    """n<i> for every pin (those with constants too) and freq, where freq reaches minsup.

    Assignments without a match are absent, as support 0 reaches no threshold.  A pattern without free nodes has support 1 where it matches.
    candidates holds columns n<i> of pins: only those assignments count.
    """
    if minsup < 1:
        raise ValueError("minsup is at least 1")
    pins = [n(i) for i in p.pins]
    if strategy == "fold":
        out = _folded(p, Edges(g, constants, allowed), minsup)
        if candidates is not None and pins:
            out = out.join(candidates, pins, "left_semi")
    elif strategy in ("expand", "probe"):
        start = candidates if strategy == "probe" and candidates is not None and pins else None
        rows = visible_rows(g, p, constants, allowed, start)
        if candidates is not None and start is None and pins:
            rows = rows.join(candidates, pins, "left_semi")
        out = rows.groupBy(*pins).agg(F.count(F.lit(1)).alias("freq"))
    elif strategy == "blocks":
        if (p.levels, p.marks) != ((0, 1, 1), FREE + PINNED + PINNED) or constants or allowed or candidates is not None:
            raise ValueError("blocks count x(#a, #b) alone, with all values of its pins")
        out = common_parents(g, minsup)
    else:
        raise ValueError(f"no strategy {strategy}")
    return out.filter(F.col("freq") >= minsup).select(*pins, "freq")


def cube_tables(g: Graph, p: Pattern, minsup: int, allowed: dict | None = None) -> DataFrame:
    """All support tables with p's hidden set: marks STRING, pins ARRAY, freq; one pass over the distinct visible rows.

    p's marks count as visible or hidden only.  Every subset of the visible nodes is a grouping set.
    """
    visible = [i for i in range(p.size) if p.marks[i] != HIDDEN]
    rows = visible_rows(g, p, None, allowed)
    if not visible:
        return rows.agg(F.count(F.lit(1)).alias("freq")).filter(f"freq >= {minsup}").select(F.lit(p.marks).alias("marks"), F.array().cast(f"array<{g.node_type}>").alias("pins"), "freq")
    names = [n(i) for i in visible]
    grouped = rows.cube(*names).agg(F.grouping_id(*names).alias("gid"), F.count(F.lit(1)).alias("freq")).filter((F.col("freq") >= minsup))
    pinned = [(i, F.col("gid").bitwiseAND(1 << (len(visible) - 1 - k)) == 0) for k, i in enumerate(visible)]
    mark = {i: F.when(is_pin, PINNED).otherwise(FREE) for i, is_pin in pinned}
    marks = F.concat(*[mark.get(i, F.lit(HIDDEN)) for i in range(p.size)])
    pins = F.array_compact(F.array(*[F.when(is_pin, F.col(n(i))) for i, is_pin in pinned]))
    return grouped.select(marks.alias("marks"), pins.alias("pins"), "freq")


def answers(g: Graph, p: Pattern, constants: dict | None = None) -> DataFrame:
    """Distinct values of the free nodes, under constants for all pins."""
    free = [n(i) for i in p.free]
    rows = visible_rows(g, p, constants)
    return rows.select(*free).distinct() if free else rows.select(F.lit(1).alias("one")).distinct()


def answer_set(g: Graph, head: tuple[int, ...], p: Pattern, constants: dict | None = None) -> DataFrame:
    """h1..hk: the head's images, repeats and pins included."""
    rows = visible_rows(g, p, constants)
    return rows.select(*[F.col(n(h)).alias(f"h{k}") for k, h in enumerate(head, 1)]).distinct()


def support(g: Graph, p: Pattern, constants: dict | None = None) -> int:
    row = support_table(g, p, constants).agg(F.sum("freq")).first()
    return row[0] or 0


def is_frequent(g: Graph, p: Pattern, constants: dict | None, minsup: int) -> bool:
    """Stops looking when minsup answers are found."""
    return answers(g, p, constants).limit(minsup).count() >= minsup
