"""Event-fed graphs: edges from a stream, windows, degree state, and refreshed support tables."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..graph import load
from ..model.pattern import Pattern
from ..operators.miner import tall
from ..plans.twig import support_table


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The events folder, or a single file, as a stream.  Watermarks need times with a zone: a time without one is read in the session's."""
    kind = spark.read.parquet(path).schema
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    single = place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(place).isFile()
    folder, _, name = path.rpartition("/")
    rows = spark.readStream.schema(kind).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", name if single else "*.parquet").parquet(folder if single else path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def edge_stream(events: DataFrame) -> DataFrame:
    """ts, src (user), dst (key of the properties)."""
    return events.select("ts", F.concat(F.lit("u:"), F.col("user_id").cast("string")).alias("src"), F.concat(F.lit("k:"), F.get_json_object("props", "$.k")).alias("dst")).filter("src is not null and dst is not null")


def fresh_edges(edges: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each edge once while its watermark lasts."""
    return edges.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["src", "dst"])


def window_support(edges: DataFrame, length: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Per window and target: how many different sources point to it (the support of x(#c)); rows after the watermark are left out."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return edges.withWatermark("ts", delay).groupBy(w.alias("w"), F.col("dst").alias("pin1")).agg(F.size(F.collect_set("src")).cast("bigint").alias("freq")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "pin1", "freq")


def session_edges(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """Edges between consecutive events of one session: user, start, src, dst (keys in the order of time)."""
    e = events.withWatermark("ts", delay).withColumn("k", F.get_json_object("props", "$.k"))
    s = e.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "k"))).alias("seq"))
    steps = F.expr("transform(slice(sequence(1, size(seq)), 1, greatest(size(seq) - 1, 0)), i -> struct(seq[i - 1].k as src, seq[i].k as dst))")
    return s.select("user_id", F.col("s.start").alias("start"), F.explode(steps).alias("x")).select("user_id", "start", "x.src", "x.dst")


class DegreeState(StatefulProcessor):
    """Out-degree of each node, from edges that are new; gives the node, its degree and how the sum of squares moved."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.seen = handle.getMapState("seen", "dst string", "n int")
        self.degree = handle.getValueState("degree", "n bigint")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        before = self.degree.get()[0] if self.degree.exists() else 0
        now = before
        for batch in rows:
            for dst in batch.dst:
                if not self.seen.containsKey((dst,)):
                    self.seen.updateValue((dst,), (1,))
                    now += 1
        self.degree.update((now,))
        yield pd.DataFrame({"src": [key[0]], "degree": [now], "moved": [now * now - before * before]})

    def close(self) -> None:
        pass


def degrees(edges: DataFrame) -> DataFrame:
    """src, degree, moved after each batch; the sums of moved and of the new edges keep the sparsity confidence current."""
    return edges.groupBy("src").transformWithStateInPandas(statefulProcessor=DegreeState(), outputStructType="src string, degree bigint, moved bigint", outputMode="Update", timeMode="None")


def two_steps(edges: DataFrame, within: str = "10 minutes", delay: str = "1 hour") -> DataFrame:
    """Stream-stream join: u to v, then within a time v to w: t1, t2, u, v, w."""
    a = edges.select(F.col("ts").alias("t1"), F.col("src").alias("u"), F.col("dst").alias("v")).withWatermark("t1", delay)
    b = edges.select(F.col("ts").alias("t2"), F.col("src").alias("v2"), F.col("dst").alias("w")).withWatermark("t2", delay)
    return a.join(b, F.expr(f"v = v2 and t2 >= t1 and t2 <= t1 + interval {within}")).select("t1", "t2", "u", "v", "w")


def return_steps(edges: DataFrame, path: str, checkpoint: str, seconds: int = 600):
    """t1, t2, u, v, w: an edge u to v, then within so many seconds an edge of another w to v; written to path/steps.  Returns the started query.

    What a join of two streams gives, whatever comes late: batches are kept in files, not in state.  Both sides meet on the node and a slot of
    time, a later edge standing in its slot and the one before, so a node's edges meet only their neighbours in time.  Of earlier batches only rows near
    the new ones are read.
    """
    slot = f"unix_micros(ts) div {seconds * 1_000_000}"
    schema = "t1 timestamp, t2 timestamp, u string, v string, w string"

    def pairs(first: DataFrame, later: DataFrame) -> DataFrame:
        a = first.selectExpr("ts as t1", "src as u", "dst as v", f"{slot} as slot")
        b = later.selectExpr("ts as t2", "dst as v", "src as w", f"explode(array({slot}, {slot} - 1)) as slot")
        return a.join(b, ["v", "slot"]).filter(f"t2 >= t1 and t2 <= t1 + interval {seconds} seconds and u <> w").select("t1", "t2", "u", "v", "w")

    def each(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.select("ts", "src", "dst").write.mode("overwrite").parquet(f"{path}/edges/batch={number}")
        rows = spark.read.parquet(f"{path}/edges").filter(F.col("batch") <= number)
        new = rows.filter(F.col("batch") == number)
        found = pairs(new, new)
        low, high = new.agg(F.unix_micros(F.min("ts")), F.unix_micros(F.max("ts"))).first()
        if number and low is not None:
            old = rows.filter((F.col("batch") < number) & F.expr(f"ts between timestamp_micros({low - seconds * 1_000_000}) and timestamp_micros({high + seconds * 1_000_000})"))
            found = found.union(pairs(new, old)).union(pairs(old, new))
        found.write.mode("overwrite").parquet(f"{path}/steps/batch={number}")

    edges.sparkSession.createDataFrame([], schema).write.mode("overwrite").parquet(f"{path}/steps/batch=-1")
    return edges.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def refresh_small(edges: DataFrame, path: str, checkpoint: str, minsup: int):
    """Each batch's new edges are appended to a snapshot, and the tables of trees of up to two nodes recomputed; returns the started query.

    Edges are only added, so supports never fall: tables of larger trees stay valid lower bounds until they are mined again.
    """
    small = [Pattern((0,), m) for m in "de"] + [Pattern((0, 1), m) for m in ("dd", "dp", "pd", "ed")]

    def each(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.select("src", "dst").write.mode("overwrite").parquet(f"{path}/edges/batch={number}")
        g = load(spark.read.parquet(f"{path}/edges"))
        rows = None
        for p in small:
            part = tall(g, p, support_table(g, p, minsup=minsup))
            rows = part if rows is None else rows.unionByName(part)
        rows.write.mode("overwrite").parquet(f"{path}/support/version={number}")

    return edges.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def run_to(df: DataFrame, path: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over what there is into a parquet folder (append) and read it back."""
    q = df.writeStream.format("parquet").outputMode(mode).option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.read.schema(df.schema).parquet(path)


def run_to_memory(df: DataFrame, name: str, mode: str = "update") -> DataFrame:
    """Run a stream over what there is into a table in memory, for small results."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def late_rows(query) -> int:
    """Rows that came after the watermark and were left out, over a query's recent progress."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p["stateOperators"])
