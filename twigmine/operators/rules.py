"""Rules between tree queries: lhs => rhs, where rhs is contained in lhs, found from stored support tables.

For a given lhs all folds of it into stored patterns are enumerated on the driver (patterns are small); a fold tells rhs head and how
lhs pins follow rhs pins, and all confident instances of all folds come from one join of the lhs table with the stored ones.
The data graph is not read again.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from fractions import Fraction
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph
from ..model.contain import Fold, contains, covers_free, fold_maps, is_fold
from ..model.pattern import Pattern, pattern_key
from ..model.query import TreeQuery, pure
from ..model.ruledup import distinct_folds
from ..model.shape import Levels, shapes
from ..plans.twig import n, support_table
from ..storage import cut
from .catalog import Tables

RULE_COLUMNS = ["lhs_key", "rhs_key", "head", "rho", "fold", "lhs_pins", "rhs_pins", "freq", "lhs_freq", "conf"]
#: Folds that are broadcast at most (about 200 bytes each).
MOST_BROADCAST = 200_000


@dataclass(frozen=True)
class Rule:
    """lhs => rhs; rho gives for every lhs pin, in preorder, the position of the rhs pin whose constant it takes."""

    lhs: TreeQuery
    rhs: TreeQuery
    rho: tuple[int, ...]

    def is_legal(self) -> bool:
        return contains(self.lhs, self.rhs, dict(zip(self.lhs.body.pins, self.rho, strict=True)))

    def lhs_constants(self, alpha: dict) -> dict:
        return {i: alpha[j] for i, j in zip(self.lhs.body.pins, self.rho, strict=True)}


def rule_of_fold(lhs: TreeQuery, rhs: Pattern, f: Fold) -> Rule:
    return Rule(lhs, TreeQuery(tuple(f[h] for h in lhs.head), rhs), tuple(f[i] for i in lhs.body.pins))


def purify_rule(rule: Rule) -> Rule:
    """lhs with a pure head, and the same places gone from the rhs head: the confidence stays."""
    place = [rule.lhs.head.index(v) for v in rule.lhs.body.free]
    return Rule(pure(rule.lhs.body), TreeQuery(tuple(rule.rhs.head[k] for k in place), rule.rhs.body), rule.rho)


def confidence(g: Graph, rule: Rule, alpha: dict | None = None) -> tuple[int, int]:
    """Supports of rhs and lhs under constants for all rhs pins; their ratio is the confidence."""
    alpha = alpha or {}
    freq = support_table(g, rule.rhs.body, alpha).agg(F.sum("freq")).first()[0] or 0
    lhs_freq = support_table(g, rule.lhs.body, rule.lhs_constants(alpha)).agg(F.sum("freq")).first()[0] or 0
    return freq, lhs_freq


def passes(freq: int, lhs_freq: int, minsup: int, minconf) -> bool:
    c = Fraction(str(minconf))
    return freq >= minsup and freq * c.denominator >= c.numerator * lhs_freq


def lhs_table(lhs: TreeQuery, store: Tables, g: Graph | None = None, minsup: int = 1) -> DataFrame:
    """lhs_pins ARRAY (preorder of the lhs pins), lhs_freq: from the database, for any equivalent form; else counted once on the graph."""
    p = lhs.body
    norm, old = p.normal()
    if len(norm.pins) == len(p.pins) and len(norm.free) == len(p.free):
        rows = store.table(norm)
        if not rows.isEmpty():
            stored = [old[i] for i in norm.pins]
            pins = F.array(*[F.col("pins")[stored.index(i)] for i in p.pins]) if p.pins else F.col("pins")
            return rows.select(pins.alias("lhs_pins"), F.col("freq").alias("lhs_freq"))
    if g is None:
        raise ValueError("the lhs is not in the database: give the graph to count it")
    counted = support_table(g, p, minsup=minsup)
    pins = F.array(*[F.col(n(i)) for i in p.pins]) if p.pins else F.array()
    return counted.select(pins.cast(f"array<{store.node_type}>").alias("lhs_pins"), F.col("freq").alias("lhs_freq"))


@dataclass
class FoldCounts:
    """Fold maps made, left with a legal head, and left after repeats are removed."""

    made: int = 0
    legal: int = 0
    kept: int = 0


def folds_into(lhs: TreeQuery, patterns: Iterable[Pattern], dedup: str = "linear", counts: FoldCounts | None = None) -> list[tuple[Pattern, Fold]]:
    """All folds of the lhs into the patterns whose head image holds every free node, without repeats."""
    counts = counts or FoldCounts()
    out = []
    for p in patterns:
        if p.height < lhs.body.height:
            continue
        made = list(fold_maps(lhs.body, p))
        legal = [f for f in made if covers_free(f, p, lhs.body) and {*p.free} <= {f[h] for h in lhs.head}]
        kept = distinct_folds(legal, lhs.body, p, dedup)
        counts.made, counts.legal, counts.kept = counts.made + len(made), counts.legal + len(legal), counts.kept + len(kept)
        out += [(p, f) for f in kept]
    return out


def name(p: Pattern, v: int, numbers: dict[int, int]) -> str:
    return f"x{v}" if v not in numbers else f"#{numbers[v]}"


def fold_rows(lhs: TreeQuery, folds: list[tuple[Pattern, Fold]]) -> list[tuple]:
    """Per fold: key of the pattern, head in names (x<node>, #<number of the pin>), rho as numbers of pins, fold."""
    rows = []
    for p, f in folds:
        numbers = {v: k for k, v in enumerate(p.pins)}
        rows.append((pattern_key(p), [name(p, f[h], numbers) for h in lhs.head], [numbers[f[i]] for i in lhs.body.pins], list(f)))
    return rows


def mine_rules(store: Tables, lhs: TreeQuery, minconf, g: Graph | None = None, dedup: str = "linear", counts: FoldCounts | None = None, patterns: Iterable[Pattern] | None = None, left: DataFrame | None = None) -> DataFrame:
    """Every rule of the lhs into the stored patterns with confidence minconf at least, all folds in one join.

    minconf: a fraction, exact ('0.3', Fraction(1, 3)).  Counts are compared by integer products.  left: the lhs table, where it is known.
    """
    c = Fraction(str(minconf))
    if not 0 <= c <= 1:
        raise ValueError("minconf is between 0 and 1")
    spark = store.support.sparkSession
    patterns = store.patterns(lhs.body.height) if patterns is None else patterns
    rows = fold_rows(lhs, folds_into(lhs, patterns, dedup, counts))
    folds = spark.createDataFrame(rows, "pattern_key string, head array<string>, rho array<int>, fold array<int>")
    folds = F.broadcast(folds) if len(rows) <= MOST_BROADCAST else folds
    right = store.support.select("pattern_key", "pins", "freq").join(folds, "pattern_key").withColumn("lhs_pins", F.expr("transform(rho, i -> pins[i])"))
    both = right.join(lhs_table(lhs, store, g) if left is None else left, "lhs_pins")
    exact = F.col("freq").cast("decimal(20,0)") * F.lit(c.denominator).cast("decimal(18,0)") >= F.col("lhs_freq").cast("decimal(20,0)") * F.lit(c.numerator).cast("decimal(18,0)")
    return both.filter(exact).select(F.lit(pattern_key(lhs.body)).alias("lhs_key"), F.col("pattern_key").alias("rhs_key"), "head", "rho", "fold", "lhs_pins", F.col("pins").alias("rhs_pins"), "freq", "lhs_freq", (F.col("freq") / F.col("lhs_freq")).alias("conf"))


def rule_table(store: Tables, lhs: TreeQuery, p: Pattern, f: Fold, minconf, g: Graph | None = None) -> DataFrame:
    """All confident instances of one fold: one join of two support tables."""
    if not is_fold(f, lhs.body, p):
        raise ValueError("not a fold map")
    return mine_rules(store, lhs, minconf, g, "none", patterns=[p]).filter(F.col("fold") == F.array(*[F.lit(x) for x in f]))


def rules_by_tree(g: Graph, lhs: TreeQuery, minsup: int, minconf, max_nodes: int | None = None, dedup: str = "linear", counts: FoldCounts | None = None) -> Iterator[tuple[Levels, DataFrame]]:
    """Rules as the search goes on: a tree, then the rules into its patterns, before the next tree is looked at.

    Trees lower than the lhs have no fold and are not mined; the lhs is counted on the graph once; nothing is kept between trees but its table.
    Without max_nodes it goes on until the caller stops.
    """
    from .miner import mine_tree

    left = None
    for levels in shapes(max_nodes, lhs.body.height):
        found = Tables(mine_tree(g, levels, minsup))
        if left is None:
            own = support_table(g, lhs.body)
            pins = F.array(*[F.col(n(i)) for i in lhs.body.pins]) if lhs.body.pins else F.array()
            left = cut(own.select(pins.cast(f"array<{found.node_type}>").alias("lhs_pins"), F.col("freq").alias("lhs_freq")), "lhs")
        yield levels, mine_rules(found, lhs, minconf, dedup=dedup, counts=counts, left=left)


def mine_rules_live(g: Graph, lhs: TreeQuery, minsup: int, minconf, max_nodes: int, dedup: str = "linear", counts: FoldCounts | None = None) -> DataFrame:
    """All rules into trees of up to max_nodes without a database: those of rules_by_tree together."""
    return reduce(DataFrame.unionByName, [found for _, found in rules_by_tree(g, lhs, minsup, minconf, max_nodes, dedup, counts)])


def count_rules(found: DataFrame) -> DataFrame:
    """instances, rhs_queries: rules counted by their constants and by the queries on their right side (pattern and fold)."""
    return found.agg(F.count(F.lit(1)).alias("instances"), F.count_distinct("rhs_key", F.array_join(F.col("fold").cast("array<string>"), ",")).alias("rhs_queries"))


def brute_rules(g: Graph, lhs: TreeQuery, patterns: Iterable[Pattern], minsup: int, minconf) -> list[tuple]:
    """Every map of nodes tried, both sides counted on the graph: (rhs key, fold, lhs pins, rhs pins, freq, lhs freq)."""
    out = []
    left = {tuple(r[:-1]): r[-1] for r in support_table(g, lhs.body, strategy="expand").collect()}
    for p in patterns:
        right = support_table(g, p, minsup=minsup, strategy="expand").collect()
        for f in product(range(p.size), repeat=lhs.body.size):
            if is_fold(f, lhs.body, p) and {*p.free} <= {f[h] for h in lhs.head}:
                for r in right:
                    alpha = dict(zip(p.pins, r[:-1], strict=True))
                    key = tuple(alpha[f[i]] for i in lhs.body.pins)
                    if key in left and passes(r[-1], left[key], minsup, minconf):
                        out.append((pattern_key(p), f, key, tuple(r[:-1]), r[-1], left[key]))
    return out


def ratio(g: Graph, lhs: Pattern, rhs: Pattern, constants: dict | None = None) -> DataFrame:
    """pin1..pinK of rhs, freq, lhs_freq of a rule whose lhs has no pins: the workhorse of single-rule workloads."""
    left = support_table(g, lhs).agg(F.sum("freq").alias("lhs_freq"))
    right = support_table(g, rhs, constants)
    open_pins = [i for i in rhs.pins if i not in (constants or {})]
    return right.crossJoin(F.broadcast(left)).select(*[F.col(n(i)).alias(f"pin{k}") for k, i in enumerate(open_pins, 1)], "freq", "lhs_freq")  # left is one row
