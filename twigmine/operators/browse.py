"""Questions to a pattern database: instances, rules, suggestions, constants that stand out.  The graph is not read."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..graph import Graph
from ..model.query import Named, TreeQuery, parse_pattern
from .catalog import Tables, diff
from .rules import mine_rules


def instances(store: Tables, pattern: str | Named, **fixed) -> DataFrame:
    """A column for every pin by its name, and freq: the frequent instances, with some pins fixed."""
    named = parse_pattern(pattern) if isinstance(pattern, str) else pattern
    p = named.pattern
    values = {named.names[i]: v for i, v in named.constants.items()} | fixed
    rows = store.table(p).select(*[F.col("pins")[k].alias(named.names[i]) for k, i in enumerate(p.pins)], "freq")
    for k, v in values.items():
        rows = rows.filter(F.col(k) == F.lit(v))
    return rows


def rules(store: Tables, lhs: TreeQuery, alpha: list | None, minconf, g: Graph | None = None, dedup: str = "linear") -> DataFrame:
    """All confident right sides of one instance of the lhs."""
    found = mine_rules(store, lhs, minconf, g, dedup)
    return found if alpha is None else found.filter(F.col("lhs_pins") == F.array(*[F.lit(a) for a in alpha]).cast(f"array<{store.node_type}>"))


def rule_instances(found: DataFrame, rhs_key: str, fold: tuple[int, ...]) -> DataFrame:
    """One right side's instances and their frequencies."""
    return found.filter((F.col("rhs_key") == rhs_key) & (F.col("fold") == F.array(*[F.lit(x) for x in fold]))).select("lhs_pins", "rhs_pins", "freq", "lhs_freq", "conf")


def suggest(store: Tables, count: int = 10, per_size: bool = True) -> DataFrame:
    """The most frequent instances, of each size or of all; ties by key and pins."""
    pins = F.concat_ws(",", F.col("pins").cast("array<string>"))
    rows = store.support.select("n_nodes", "pattern_key", pins.alias("pins"), "freq")
    if not per_size:
        return rows.orderBy(F.desc("freq"), "pattern_key", "pins").limit(count)
    # Spark keeps only count rows of a size on each task before the shuffle.
    order = Window.partitionBy("n_nodes").orderBy(F.desc("freq"), "pattern_key", "pins")
    return rows.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= count)


def hot_constants(store: Tables, count: int = 10) -> DataFrame:
    """Constants by the number of different patterns and of instances they stand in."""
    rows = store.support.select("pattern_key", F.explode("pins").alias("constant"))
    return rows.groupBy("constant").agg(F.count_distinct("pattern_key").alias("patterns"), F.count(F.lit(1)).alias("instances")).orderBy(F.desc("patterns"), F.desc("instances"), "constant").limit(count)


def compare(a: Tables, b: Tables) -> DataFrame:
    return diff(a.support, b.support)


def shares(store: Tables, g: Graph) -> DataFrame:
    """pattern_key, pins, freq, share: the support as a share of the graph's nodes."""
    nodes = g.nodes.agg(F.count(F.lit(1)).alias("n"))
    return store.support.crossJoin(F.broadcast(nodes)).select("pattern_key", "pins", "freq", (F.col("freq") / F.col("n")).alias("share"))  # nodes is one row
