"""Search for all frequent patterns: trees by growing size outside, hidden and pinned nodes level by level inside.

Trees never prune each other: a larger tree may have more answers than the ones within it.  On one tree, hiding or pinning
a node never raises a support, so a pattern is looked at only if all its parents (one hidden or pinned node less) have frequent assignments,
and a pin takes only values that it takes in a parent's table.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph
from ..model.pattern import FREE, HIDDEN, PINNED, Pattern, all_marks, pattern_key, pattern_of_key
from ..model.shape import Levels, shapes, tree_key
from ..plans.twig import cube_tables, n, support, support_table
from ..storage import cut
from .catalog import COLUMNS, Catalog, Tables, empty, own_order

#: Patterns counted by one job: what bounds the size of its plan; fewer in wide graphs, where a pattern's plan has several parts.
PER_JOB, PER_JOB_WIDE = 3, 1
#: Rows that the grouping sets of one tree may make for the search to choose them.
MOST_CUBE = 20_000_000
#: Levels at which pins may only take their parents' values: below, every node is a candidate anyway.
FIRST_RESTRICTED = 2
#: Rows of a parent's table up to which it restricts the pins in a wide graph: larger ones cost more to read and meet than they leave out, as bounds
#: have left out most before (twig.py).
MOST_ALLOWED = 500_000


@dataclass
class Budget:
    """When to stop: tree size, wall clock, number of patterns, or the caller's own word after any tree."""

    max_nodes: int | None = None
    seconds: float | None = None
    max_patterns: int | None = None
    stop: Callable[[Metrics], bool] | None = None

    def spent(self, m: Metrics) -> bool:
        return bool(self.seconds is not None and m.wall_s >= self.seconds or self.max_patterns is not None and m.patterns >= self.max_patterns or self.stop and self.stop(m))


@dataclass
class Metrics:
    """What a run did: seconds, instantiated patterns, patterns with a table, support queries, and what was pruned and why."""

    started: float = field(default_factory=time.monotonic)
    patterns: int = 0
    classes: int = 0
    support_queries: int = 0
    jobs: int = 0
    trees: int = 0
    pruned: dict[str, int] = field(default_factory=lambda: {"parent": 0, "redundant": 0, "copy": 0})
    steps: list[tuple[str, int, float]] = field(default_factory=list)
    cut_short: bool = False

    @property
    def wall_s(self) -> float:
        return time.monotonic() - self.started

    def seconds_per_pattern(self) -> float | None:
        """Slope of the wall clock over the number of patterns found so far, by least squares over the trees."""
        xs, ys = [c for _, c, _ in self.steps], [s for *_, s in self.steps]
        k = len(xs)
        if k < 2 or len(set(xs)) < 2:
            return None
        mx, my = sum(xs) / k, sum(ys) / k
        return sum((x - mx) * (y - my) for x, y in zip(xs, ys, strict=True)) / sum((x - mx) ** 2 for x in xs)


@dataclass
class Mined:
    tables: Tables
    metrics: Metrics


def tall(g: Graph, p: Pattern, table: DataFrame) -> DataFrame:
    """A pattern's wide table as rows of the tall one, pins in canonical order."""
    canonical, old = p.canonize()
    pins = F.array(*[F.col(n(old[i])) for i in canonical.pins]) if canonical.pins else F.array()
    return table.select(F.lit(p.size).alias("n_nodes"), F.lit(canonical.tree_key).alias("tree_key"), F.lit(canonical.refined()).alias("pattern_key"), F.lit(p.level).alias("level"), pins.cast(f"array<{g.node_type}>").alias("pins"), F.col("freq").cast("bigint").alias("freq"))


def candidates(p: Pattern, store: Tables, g: Graph) -> DataFrame:
    """n<i> for every pin: the assignments whose every generalisation is frequent, as the natural join of all parents' tables.

    Parents without pins are gates: without a row they empty the result.  A lone first-level pin takes every node.  Two parents
    that share no pin would pair all their values; the search itself therefore meets every parent's table where its pins come together (support_table's allowed).
    """
    if not p.pins:
        raise ValueError("a pattern without pins has no candidate assignments")
    tables = [(q, store.wide(q).drop("freq")) for q in p.parents()]
    own = sorted((t for q, t in tables if q.pins), key=lambda t: -len(t.columns))
    if not own:
        out = g.nodes.select(F.col("id").alias(n(p.pins[0])))
    else:
        out = own[0]
        for t in own[1:]:
            shared = [c for c in t.columns if c in out.columns]
            out = out.join(t, shared) if shared else out.crossJoin(t)
    for q in p.parents():
        if not q.pins:
            # A gate is one row or none, read as a truth value.
            if store.table(q).isEmpty():
                out = out.limit(0)
    return out.select(*[n(i) for i in p.pins]).distinct()


def allowed_values(parents: Iterable[Pattern], store: Tables | Placed) -> dict[tuple[int, ...], DataFrame]:
    """The candidate assignments of a pattern, as a table of values for each set of pins that one of its stored parents has.

    Only assignments that stand in every one of the tables are counted: their natural join, without ever being made.
    """
    out: dict[tuple[int, ...], DataFrame] = {}
    for q in parents:
        if q.pins:
            rows = store.wide(q).drop("freq")
            out[q.pins] = out[q.pins].join(rows, [n(i) for i in q.pins], "left_semi") if q.pins in out else rows
    return out


class Placed:
    """Tables of patterns, each in the file that it was written to with few others: a parent's table is one scan in a plan, not one for each file of the search."""

    def __init__(self):
        self.files: dict[str, DataFrame] = {}

    def put(self, patterns: Iterable[Pattern], rows: DataFrame) -> None:
        self.files |= {pattern_key(p): rows for p in patterns}

    def wide(self, p: Pattern) -> DataFrame:
        return Tables(self.files[pattern_key(p)]).wide(p)


def level_patterns(levels: Levels, kept: set[str], current: list[Pattern], dedup: str, metrics: Metrics) -> list[Pattern]:
    """The next level from the patterns of this one that have rows; kept holds the canonical keys with rows."""
    seen, out = set(), []
    for p in current:
        for q in p.extensions():
            if q in seen:
                continue
            seen.add(q)
            if dedup in ("redundancy", "full") and q.has_redundancy():
                metrics.pruned["redundant"] += 1
            elif dedup in ("canonical", "full") and not q.is_canonical():
                metrics.pruned["copy"] += 1
            elif any(pattern_key(r) not in kept for r in q.parents() if not (dedup in ("redundancy", "full") and r.has_redundancy())):
                metrics.pruned["parent"] += 1
            else:
                out.append(q)
    return out


def mine_tree(g: Graph, levels: Levels, minsup: int, dedup: str = "full", order: str = "level", strategy: str = "fold", metrics: Metrics | None = None, budget: Budget | None = None) -> DataFrame:
    """The support tables of one tree, written level by level; a budget that is spent between two levels ends it, and metrics.cut_short says so.

    order 'level' runs all patterns with as many hidden and pinned nodes in one job; 'double' runs hidden sets by size outside and
    pinned sets by size inside.  dedup: none, redundancy, canonical or full.  With dedup none or redundancy, copies of a pattern
    give the same rows; they are counted in the metrics and stored once.
    """
    metrics = metrics or Metrics()
    out, kept, rows, sizes, store = empty(g.spark, g.node_type), set(), [], {}, Placed()
    batches: dict[tuple, set[Pattern]] = {(0,): {Pattern(levels, FREE * len(levels))}} if order == "level" else {(0, 0): {Pattern(levels, FREE * len(levels))}}
    while batches:
        if rows and budget and budget.spent(metrics):
            metrics.cut_short = True
            break
        at = min(batches)
        batch = sorted(batches.pop(at), key=lambda p: p.marks)
        # With the double order a parent may have been pruned after its child was put down.
        batch = [p for p in batch if all(pattern_key(q) in kept for q in p.parents() if not (dedup in ("redundancy", "full") and q.has_redundancy()))]
        if not batch:
            continue
        parts = []
        for p in batch:
            allowed = allowed_values((q for q in p.parents() if not (dedup in ("redundancy", "full") and q.has_redundancy()) and not (g.wide and sizes[pattern_key(q)] > MOST_ALLOWED)), store) if p.level >= FIRST_RESTRICTED and p.pins else {}
            parts.append(tall(g, p, support_table(g, p, minsup=minsup, strategy=strategy, allowed=allowed)))
        metrics.support_queries += len(batch)
        at_once = PER_JOB_WIDE if g.wide else PER_JOB
        metrics.jobs += -(-len(parts) // at_once)
        files = []
        for k in range(0, len(parts), at_once):
            files.append(cut(reduce(DataFrame.unionByName, parts[k : k + at_once]), "level"))
            store.put(batch[k : k + at_once], files[-1])
        found = reduce(DataFrame.unionByName, files)
        if dedup in ("none", "redundancy"):
            found = cut(found.distinct(), "level")
            store.put(batch, found)
        counts = {r.pattern_key: r["count"] for r in found.groupBy("pattern_key").count().collect()}
        kept |= counts.keys()
        sizes |= counts
        metrics.patterns += sum(counts.values())
        metrics.classes += len(counts)
        rows.append(found)
        out = reduce(DataFrame.unionByName, rows)
        alive = [p for p in batch if pattern_key(p) in counts]
        for q in level_patterns(levels, kept, alive, dedup, metrics) if order == "level" else _later(alive, dedup, metrics):
            key = (q.level,) if order == "level" else (len(q.hidden), len(q.pins))
            batches.setdefault(key, set()).add(q)
    return out


def _later(alive: list[Pattern], dedup: str, metrics: Metrics) -> Iterable[Pattern]:
    for p in alive:
        for q in p.extensions():
            if dedup in ("redundancy", "full") and q.has_redundancy():
                metrics.pruned["redundant"] += 1
            elif dedup in ("canonical", "full") and not q.is_canonical():
                metrics.pruned["copy"] += 1
            else:
                yield q


def mine_tree_cube(g: Graph, levels: Levels, minsup: int, metrics: Metrics) -> DataFrame:
    """One grouping-sets query for each hidden set whose plain support is frequent, of hidden sets that are copies of each other the canonical one.

    A pattern is read off the first marking of its class over such a hidden set, its pins brought into the canonical order.
    """
    plain = []
    for p in (Pattern(levels, "".join(m)) for m in product(FREE + HIDDEN, repeat=len(levels))):
        if p.has_redundancy():
            metrics.pruned["redundant"] += 1
        elif not p.is_canonical():
            metrics.pruned["copy"] += 1
        else:
            plain.append(p)
    gates = [support_table(g, p, minsup=minsup).select(F.lit(p.marks).alias("marks")) for p in plain]
    frequent = {r[0] for r in reduce(DataFrame.union, gates).collect()}
    metrics.pruned["parent"] += len(plain) - len(frequent)
    metrics.support_queries += len(plain) + len(frequent)
    metrics.jobs += 1 + bool(frequent)
    if not frequent:
        return empty(g.spark, g.node_type)
    classes: dict[str, tuple] = {}
    for p in all_marks(levels, "redundancy"):
        if p.marks.replace(PINNED, FREE) in frequent:
            canonical, old = p.canonize()
            classes.setdefault(canonical.refined(), (p.marks, canonical.refined(), p.level, [p.pins.index(old[i]) for i in canonical.pins]))
    wanted = g.spark.createDataFrame(list(classes.values()), "marks string, pattern_key string, level int, perm array<int>")
    found = reduce(DataFrame.unionByName, [cube_tables(g, p, minsup) for p in plain if p.marks in frequent]).join(F.broadcast(wanted), "marks")  # at most 3 ** nodes rows
    found = found.select(F.lit(len(levels)).alias("n_nodes"), F.lit(tree_key(levels)).alias("tree_key"), "pattern_key", "level", F.expr("transform(perm, i -> pins[i])").alias("pins"), "freq")
    found = cut(found, "cube")
    counts = found.groupBy("pattern_key").count().collect()
    metrics.patterns += sum(r["count"] for r in counts)
    metrics.classes += len(counts)
    return found


def mine(g: Graph, minsup: int, max_nodes: int | None = None, dedup: str = "full", order: str = "level", strategy: str = "fold", budget: Budget | None = None, catalog: Catalog | None = None, min_height: int = 0, run: str = "") -> Mined:
    """All patterns of support minsup or more, tree by tree, until the budget is spent.

    strategy: fold or expand (support tables), cube, or auto: cube where a tree's matches times its grouping sets stay below MOST_CUBE, else fold.
    With a catalog every finished tree is written there and skipped when the search is taken up again; the catalog must be of this graph, threshold and
    dedup.  A tree that the budget cuts short is written as far as it came and counted anew the next time.  order='double' with dedup='none' is the
    plain double levelwise search.
    """
    if minsup < 1:
        raise ValueError("minsup is at least 1")
    budget = budget or Budget()
    max_nodes = max_nodes or budget.max_nodes
    if max_nodes is None and budget.seconds is None and budget.max_patterns is None and budget.stop is None:
        raise ValueError("the set of frequent patterns may be infinite: give a bound")
    metrics, parts = Metrics(), []
    if catalog:
        catalog.claim(g.identity(), minsup, "full" if strategy in ("cube", "auto") else dedup)
    finished = catalog.finished() if catalog else set()
    if strategy in ("fold", "auto"):
        g = g.told_apart()
    for levels in shapes(max_nodes, min_height):
        if budget.spent(metrics):
            break
        if tree_key(levels) in finished:
            continue
        how = strategy
        if strategy == "auto":
            matches = support(g, Pattern(levels, FREE * len(levels)))
            how = "cube" if matches * 2 ** len(levels) <= MOST_CUBE else "fold"
        found = mine_tree_cube(g, levels, minsup, metrics) if how == "cube" else mine_tree(g, levels, minsup, dedup, order, how, metrics, budget)
        metrics.trees += 1
        metrics.steps.append((tree_key(levels), metrics.patterns, metrics.wall_s))
        if catalog:
            catalog.write(tree_key(levels), found, run, not metrics.cut_short)
        else:
            parts.append(found)
    if catalog:
        return Mined(catalog, metrics)
    return Mined(Tables(reduce(DataFrame.unionByName, parts).select(*COLUMNS) if parts else empty(g.spark, g.node_type)), metrics)


def flock(g: Graph, p: Pattern, minsup: int, strategy: str = "fold") -> Mined:
    """The search with the user's pattern fixed: its hidden nodes stay, its pins come level by level."""
    metrics = Metrics()
    bare = Pattern(p.levels, p.marks.replace(PINNED, FREE))
    rows, level, kept, allowed_rows = [], [bare], set(), empty(g.spark, g.node_type)
    while level:
        parts = [tall(g, q, support_table(g, q, minsup=minsup, strategy=strategy, allowed=allowed_values((q.marked(i, FREE) for i in q.pins), Tables(allowed_rows)) if len(q.pins) > 1 else None)) for q in level]
        metrics.support_queries += len(level)
        metrics.jobs += 1
        found = reduce(DataFrame.unionByName, parts).dropDuplicates(["pattern_key", "pins"])
        found = cut(found, "flock")
        counts = {r.pattern_key: r["count"] for r in found.groupBy("pattern_key").count().collect()}
        metrics.patterns += sum(counts.values())
        kept |= counts.keys()
        rows.append(found)
        allowed_rows = reduce(DataFrame.unionByName, rows)
        up = {q.marked(i, PINNED) for q in level if pattern_key(q) in counts for i in p.pins if q.marks[i] == FREE}
        level = sorted((q for q in up if all(pattern_key(q.marked(i, FREE)) in kept for i in q.pins)), key=lambda q: q.marks)
    return Mined(Tables(allowed_rows), metrics)


def per_instance(g: Graph, p: Pattern, minsup: int, most: int = 200) -> list[tuple[tuple, int]]:
    """The baseline without tables: one count for each assignment of the pins, for graphs of at most most assignments."""
    from itertools import product

    ids = [r[0] for r in g.nodes.orderBy("id").limit(most + 1).collect()]
    if len(ids) ** len(p.pins) > most:
        raise ValueError("too many assignments to count one by one")
    out = []
    for values in product(ids, repeat=len(p.pins)):
        found = support_table(g, p, dict(zip(p.pins, values, strict=True)), minsup, "expand").collect()
        out += [(values, r.freq) for r in found]
    return out


def brute_force(g: Graph, minsup: int, max_nodes: int, dedup: str = "full") -> DataFrame:
    """Every pattern counted by the plain join, nothing pruned: what the searches must give."""
    parts = [tall(g, p, support_table(g, p, minsup=minsup, strategy="expand")) for levels in shapes(max_nodes) for p in all_marks(levels, dedup)]
    return reduce(DataFrame.unionByName, parts)


def reduced_rows(rows: DataFrame) -> DataFrame:
    """Rows of a search that kept redundant patterns, brought to the canonical forms without redundancy; copies fall together."""
    keys = [r[0] for r in rows.select("pattern_key").distinct().collect()]
    table = []
    for k in keys:
        p = pattern_of_key(k)
        norm, old = p.normal()
        table.append((k, norm.size, norm.tree_key, norm.refined(), norm.level, [p.pins.index(old[i]) for i in norm.pins]))
    names = rows.sparkSession.createDataFrame(table, "pattern_key string, n2 int, t2 string, k2 string, l2 int, perm array<int>")
    moved = rows.join(F.broadcast(names), "pattern_key")  # one row per pattern
    return moved.select(F.col("n2").alias("n_nodes"), F.col("t2").alias("tree_key"), F.col("k2").alias("pattern_key"), F.col("l2").alias("level"), F.expr("transform(perm, i -> pins[i])").alias("pins"), "freq").distinct()


__all__ = ["Budget", "HIDDEN", "Metrics", "Mined", "allowed_values", "brute_force", "candidates", "flock", "mine", "mine_tree", "own_order", "per_instance", "reduced_rows", "tall"]
