"""Reading edge lists, and making edges from other tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..graph import Graph, load

FORMATS = ("parquet", "csv", "json", "orc", "text", "table", "jdbc")


def read_edges(spark: SparkSession, fmt: str, path: str | None = None, src: str = "src", dst: str = "dst", node_type: str = "string", count_dropped: bool = False, **options) -> Graph:
    """An edge list with a stated schema.  text: two words a line, parted by the option sep (blank); table: a catalog table."""
    if fmt not in FORMATS:
        raise ValueError(f"no format {fmt}; there are {', '.join(FORMATS)}")
    if fmt == "table":
        rows = spark.table(path)
    elif fmt == "text":
        parts = F.split(F.trim("value"), options.pop("sep", r"\s+"))
        rows = spark.read.text(path, **options).filter(F.size(parts) >= 2).select(parts[0].cast(node_type).alias(src), parts[1].cast(node_type).alias(dst))
    elif fmt in ("csv", "json"):
        rows = spark.read.format(fmt).options(**options).schema(f"`{src}` {node_type}, `{dst}` {node_type}").load(path)
    else:
        rows = spark.read.format(fmt).options(**options).load(*([path] if path else []))
    return load(rows, src, dst, count_dropped)


def node_key(df: DataFrame, column: str, prefix: str = ""):
    """Any atomic value as a node's string key: timestamps in ISO 8601, numbers and decimals as they print."""
    kind = df.schema[column].dataType.simpleString()
    text = F.date_format(column, "yyyy-MM-dd'T'HH:mm:ss.SSSSSS") if kind.startswith("timestamp") else F.col(column).cast("string")
    return F.concat(F.lit(prefix), text)


def edges_from(df: DataFrame, src: str, dst: str, ns_src: str = "", ns_dst: str = "") -> Graph:
    """A graph from two columns of any query, each with its own namespace."""
    return load(df.select(node_key(df, src, ns_src).alias("src"), node_key(df, dst, ns_dst).alias("dst")))


def store_bucketed(g: Graph, name: str, buckets: int) -> None:
    """The edges twice as tables, bucketed and sorted by either end, so joins on that end need no shuffle."""
    for key, suffix in (("src", "by_src"), ("dst", "by_dst")):
        g.edges.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(f"{name}_{suffix}")


def register_views(g: Graph, support: DataFrame | None = None, rules: DataFrame | None = None) -> None:
    """edge, nodes and, if given, support and rules as views for SQL."""
    g.edges.createOrReplaceTempView("edge")
    g.nodes.createOrReplaceTempView("nodes")
    for name, df in (("support", support), ("rules", rules)):
        if df is not None:
            df.createOrReplaceTempView(name)


def close_pairs(events: DataFrame, seconds: int, key: str = "user_id", ts: str = "ts", node: str = "event_id") -> DataFrame:
    """a, b: events of one key at most so many seconds apart, a before b.

    A range join by time buckets: each event stands in its bucket and its right sides in two, so only neighbours meet.
    """
    e = events.select(F.col(key).alias("key"), F.col(ts).alias("t"), F.col(node).alias("node"), F.floor(F.unix_timestamp(ts) / seconds).alias("slot"))
    right = e.select("key", F.col("t").alias("t2"), F.col("node").alias("b"), F.explode(F.array("slot", F.col("slot") - 1)).alias("slot"))
    later = (F.col("t2") > F.col("t")) | (F.col("t2") == F.col("t")) & (F.col("b") > F.col("node"))
    near = F.unix_micros(F.col("t2").cast("timestamp")) - F.unix_micros(F.col("t").cast("timestamp")) <= seconds * 1_000_000
    return e.join(right, ["key", "slot"]).filter(later & near).select(F.col("node").alias("a"), "b")


def last_before(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """As-of join: left with the value of the last row of right for the same key at or before its time (null if none).

    Both sides in one sorted pass per key; right rows go before left ones of one time."""
    both = left.select(key, ts, F.lit(1).alias("side"), F.struct(*left.columns).alias("row"), F.lit(None).cast(right.schema[value].dataType).alias("v"))
    both = both.unionByName(right.select(key, ts, F.lit(0).alias("side"), F.lit(None).cast(both.schema["row"].dataType).alias("row"), F.col(value).alias("v")))
    order = Window.partitionBy(key).orderBy(ts, "side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("found", F.last("v", ignorenulls=True).over(order)).filter("side = 1").select("row.*", F.col("found").alias(f"last_{value}"))
