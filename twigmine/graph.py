"""A data graph: the set of edges (src, dst) and what is known about it."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .storage import cut

#: Dictionaries and edge sets up to this many rows may be broadcast (about 40 bytes a row).
MOST_BROADCAST = 1_000_000
#: Pairs of children of one node, over all nodes, above which a graph is wide.
MOST_PAIRS = 2_000_000


@dataclass
class Graph:
    """Edges without duplicates and without null ends; nodes are the ends of edges, of any one atomic type."""

    edges: DataFrame
    dropped: int = 0
    wide: bool = False
    _kept: dict = field(default_factory=dict, repr=False)

    @cached_property
    def node_type(self) -> str:
        return self.edges.schema["src"].dataType.simpleString()

    @cached_property
    def nodes(self) -> DataFrame:
        return self.edges.select(F.col("src").alias("id")).union(self.edges.select("dst")).distinct()

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def persisted(self) -> Graph:
        """With the edges kept by Spark, spilling to disk: for searches that read them again and again."""
        from pyspark import StorageLevel

        return Graph(self.edges.persist(StorageLevel.MEMORY_AND_DISK), self.dropped)

    def release(self) -> None:
        self.edges.unpersist()

    def stored(self) -> Graph:
        """With the edges written to the shared folder: for searches that read them again and again and leave nothing in memory."""
        return Graph(cut(self.edges, "edges"), self.dropped)

    def told_apart(self) -> Graph:
        """A graph with very many pairs of children of one node as a wide one: its edges have a column lone, whether the end has no other parent.  Others as they are."""
        pairs = self.edges.groupBy("src").count().agg(F.sum(F.col("count") * F.col("count"))).first()[0] or 0
        if self.wide or pairs <= MOST_PAIRS:
            return self
        parents = self.edges.groupBy("dst").agg((F.count(F.lit(1)) == 1).alias("lone"))
        return Graph(cut(self.edges.join(parents, "dst").select("src", "dst", "lone"), "apart"), self.dropped, True)

    def identity(self) -> str:
        """Number of edges and a sum of their hashes: equal for equal graphs, whatever their order."""
        n, a = self.edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64(F.col("src").cast("string"), F.col("dst").cast("string")).cast("decimal(38,0)"))).first()
        return f"{n}:{a or 0}"


def load(edges: DataFrame, src: str = "src", dst: str = "dst", count_dropped: bool = False) -> Graph:
    """A graph from any two columns: rows with a null end are left out (and counted on request), duplicates removed."""
    pair = edges.select(F.col(src).alias("src"), F.col(dst).alias("dst"))
    whole = pair.filter("src is not null and dst is not null")
    dropped = pair.filter("src is null or dst is null").count() if count_dropped else 0
    return Graph(whole.distinct(), dropped)


def symmetric(g: Graph) -> Graph:
    """Both directions of every edge."""
    return Graph(g.edges.union(g.edges.select("dst", "src")).distinct())


def with_node_labels(g: Graph, labels: DataFrame, prefix: str = "label:") -> Graph:
    """labels(id, label) as further edges from a node to its label's own node."""
    return load(g.edges.select(F.col("src").cast("string"), F.col("dst").cast("string")).union(labels.select(F.col("id").cast("string"), F.concat(F.lit(prefix), F.col("label").cast("string")))))


def reify_edge_labels(edges: DataFrame, prefix: str = "label:") -> Graph:
    """edges(src, dst, label, edge_id): each edge becomes a node between its ends, with an edge to its label."""
    e = F.col("edge_id").cast("string")
    ends = F.array(F.struct(F.col("src").cast("string").alias("src"), e.alias("dst")), F.struct(e.alias("src"), F.col("dst").cast("string").alias("dst")), F.struct(e.alias("src"), F.concat(F.lit(prefix), F.col("label").cast("string")).alias("dst")))
    return load(edges.select(F.explode(ends).alias("x")).select("x.*"))


def dictionary(g: Graph) -> DataFrame:
    """id BIGINT, key: numbers of the nodes in the order of their keys.

    Keys are range-partitioned and numbered within a partition; a partition starts where the ones before it end.  Only the
    partitions' sizes come to the driver."""
    placed = g.nodes.select(F.col("id").alias("key")).repartitionByRange("key").sortWithinPartitions("key")
    # Written, so that a partition computed again can't cut the keys elsewhere.
    placed = cut(placed.withColumn("part", F.spark_partition_id()), "names")
    sizes = placed.groupBy("part").count().orderBy("part").collect()
    start, at = {}, 0
    for r in sizes:
        start[r["part"]], at = at, at + r["count"]
    if not start:
        return placed.select(F.lit(0).cast("bigint").alias("id"), "key")
    offset = F.create_map(*[F.lit(x) for kv in start.items() for x in kv])[F.col("part")]
    order = Window.partitionBy("part").orderBy("key")
    return placed.select((offset + F.row_number().over(order) - 1).cast("bigint").alias("id"), "key")


def encode(g: Graph, names: DataFrame | None = None) -> tuple[Graph, DataFrame]:
    """The graph over BIGINT ids, and its dictionary."""
    names = dictionary(g) if names is None else names
    edges = g.edges.join(names.select(F.col("key").alias("src"), F.col("id").alias("s")), "src").join(names.select(F.col("key").alias("dst"), F.col("id").alias("d")), "dst")
    return Graph(edges.select(F.col("s").alias("src"), F.col("d").alias("dst"))), names


def decode(df: DataFrame, names: DataFrame, columns: list[str]) -> DataFrame:
    """Ids in the columns back to keys."""
    for c in columns:
        df = df.join(names.select(F.col("id").alias(c), F.col("key").alias(f"_{c}")), c, "left").drop(c).withColumnRenamed(f"_{c}", c)
    return df


def stats(g: Graph) -> DataFrame:
    """edges, nodes, sum of squared out-degrees, largest out-degree and in-degree: one row."""
    out = g.edges.groupBy("src").count()
    into = g.edges.groupBy("dst").count()
    a = out.agg(F.coalesce(F.sum("count"), F.lit(0)).cast("bigint").alias("n_edges"), F.coalesce(F.sum(F.col("count") * F.col("count")), F.lit(0)).cast("bigint").alias("sum_out2"), F.max("count").alias("max_out"))
    b = into.agg(F.max("count").alias("max_in"))
    n = g.nodes.agg(F.count(F.lit(1)).alias("n_nodes"))
    return a.crossJoin(b).crossJoin(n).select("n_edges", "n_nodes", "sum_out2", "max_out", "max_in")  # one row each


def sparsity_confidence(g: Graph) -> DataFrame:
    """edges / sum of squared out-degrees: the share of pairs of children of one node that are equal."""
    d = g.edges.groupBy("src").count()
    return d.agg(F.sum("count").cast("bigint").alias("freq"), F.sum(F.col("count") * F.col("count")).cast("bigint").alias("lhs_freq"))


def edge_share(g: Graph) -> DataFrame:
    """pin1, freq, lhs_freq: how many of all edges point to each node."""
    total = g.edges.agg(F.count(F.lit(1)).alias("lhs_freq"))
    return g.edges.groupBy(F.col("dst").alias("pin1")).agg(F.count(F.lit(1)).alias("freq")).crossJoin(F.broadcast(total))


def node_share(g: Graph) -> DataFrame:
    """pin1, freq, lhs_freq: how many of the nodes that have children point to each node."""
    total = g.edges.agg(F.count_distinct("src").alias("lhs_freq"))
    return g.edges.groupBy(F.col("dst").alias("pin1")).agg(F.count(F.lit(1)).alias("freq")).crossJoin(F.broadcast(total))


def extension_share(g: Graph) -> DataFrame:
    """freq, lhs_freq: how many of all edges end at a node that has children."""
    starts = g.edges.select(F.col("src").alias("dst")).distinct()
    marked = g.edges.join(starts.withColumn("more", F.lit(1)), "dst", "left")
    return marked.agg(F.count("more").alias("freq"), F.count(F.lit(1)).alias("lhs_freq"))
