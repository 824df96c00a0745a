"""Pattern database: the support tables of all processed trees in one tall table."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.pattern import Pattern, pattern_key, pattern_of_key

COLUMNS = ["n_nodes", "tree_key", "pattern_key", "level", "pins", "freq"]


def schema(node_type: str) -> str:
    return f"n_nodes int, tree_key string, pattern_key string, level int, pins array<{node_type}>, freq bigint"


def empty(spark: SparkSession, node_type: str) -> DataFrame:
    return spark.createDataFrame([], schema(node_type))


def own_order(df: DataFrame, p: Pattern) -> DataFrame:
    """Pins stored in the order of p's canonical form, in p's own order."""
    canonical, old = p.canonize()
    stored = [old[i] for i in canonical.pins]
    return df.withColumn("pins", F.array(*[F.col("pins")[stored.index(i)] for i in p.pins]) if p.pins else F.col("pins"))


@dataclass
class Tables:
    """Support tables in a DataFrame."""

    support: DataFrame

    @property
    def node_type(self) -> str:
        return self.support.schema["pins"].dataType.elementType.simpleString()

    def table(self, p: Pattern) -> DataFrame:
        """pins (in p's order) and freq of any isomorphic form of a stored pattern."""
        rows = self.support.filter((F.col("n_nodes") == p.size) & (F.col("tree_key") == p.canonize()[0].tree_key) & (F.col("pattern_key") == pattern_key(p)))
        return own_order(rows.select("pins", "freq"), p)

    def wide(self, p: Pattern) -> DataFrame:
        """One column per pin, n<position>, and freq."""
        return self.table(p).select(*[F.col("pins")[k].alias(f"n{i}") for k, i in enumerate(p.pins)], "freq")

    def pinless(self) -> DataFrame:
        return self.support.filter(F.size("pins") == 0).select("pattern_key", "freq")

    def keys(self) -> list[str]:
        """Keys of the stored patterns, by size and level: as many as patterns, not rows."""
        return [r[0] for r in self.support.groupBy("pattern_key", "n_nodes", "level").count().orderBy("n_nodes", "level", "pattern_key").select("pattern_key").collect()]

    def patterns(self, min_height: int = 0) -> list[Pattern]:
        return [p for p in map(pattern_of_key, self.keys()) if p.height >= min_height]


class Catalog(Tables):
    """Tables in a folder of parquet files, partitioned by size and tree, with the list of finished trees.

    One catalog holds one database: of one graph, one threshold, and one way of leaving out equivalent patterns.
    """

    def __init__(self, spark: SparkSession, path: str, node_type: str = "string"):
        self.spark, self.path, self._type = spark, path, node_type

    def _read(self, name: str, schema_text: str) -> DataFrame:
        hadoop = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        if not hadoop.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(hadoop):
            return self.spark.createDataFrame([], schema_text)
        return self.spark.read.schema(schema_text).parquet(f"{self.path}/{name}")

    @property
    def support(self) -> DataFrame:
        return self._read("support", schema(self._type)).select(*COLUMNS)

    @property
    def node_type(self) -> str:
        return self._type

    def claim(self, graph_id: str, minsup: int, dedup: str) -> None:
        """Say what the tables are of; ValueError if those stored are of another graph or threshold or were left out in another way."""
        own = (graph_id, minsup, dedup)
        held = {tuple(r) for r in self._read("_database", "graph_id string, minsup int, dedup string").distinct().collect()}
        if held - {own}:
            raise ValueError(f"the catalog holds tables of {sorted(held - {own})}, not of {own}")
        if not held:
            self.spark.createDataFrame([own], "graph_id string, minsup int, dedup string").coalesce(1).write.mode("append").parquet(f"{self.path}/_database")

    def write(self, tree_key: str, df: DataFrame, run: str = "", whole: bool = True) -> None:
        """Store a tree's tables and mark it finished if they are whole.  Writing a tree again replaces it."""
        rows = df.withColumn("n_nodes", F.lit(len(tree_key.split("-")))).withColumn("tree_key", F.lit(tree_key)).select(*COLUMNS)
        rows.write.partitionBy("n_nodes", "tree_key").option("partitionOverwriteMode", "dynamic").mode("overwrite").parquet(f"{self.path}/support")
        if not whole:
            return
        self.spark.createDataFrame([(tree_key, run)], "tree_key string, run string").coalesce(1).write.mode("append").parquet(f"{self.path}/_finished")

    def finished(self, run: str | None = None) -> set[str]:
        done = self._read("_finished", "tree_key string, run string")
        return {r.tree_key for r in (done if run is None else done.filter(F.col("run") == run)).distinct().collect()}

    def export(self, path: str, p: Pattern, fmt: str = "csv") -> None:
        """A pattern's wide table in another format."""
        self.wide(p).write.format(fmt).option("header", "true").mode("overwrite").save(path)


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of two databases that are not in both with one count: pattern_key, pins, freq_a, freq_b."""
    left, right = (x.select("pattern_key", "pins", F.col("freq").alias(f"freq_{s}")) for x, s in ((a, "a"), (b, "b")))
    return left.join(right, ["pattern_key", "pins"], "full").filter(~F.col("freq_a").eqNullSafe(F.col("freq_b")))
