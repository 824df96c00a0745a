"""Streams over the given events, run to their end; each gives what a batch query over the same rows gives."""

from __future__ import annotations

from uuid import uuid4

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.datagraphs import table
from ..sources.synthetic import copy_model_on, uniform_on, uniform_on_native
from ..storage import shared_folder
from . import stream


#: A delay longer than any input: no row comes late, whatever the order of files.
COVERS = "3650 days"


def _place(spark: SparkSession, name: str) -> tuple[str, str]:
    root = f"{shared_folder(spark)}/{name}-{uuid4().hex}"
    return f"{root}/out", f"{root}/checkpoint"


def _edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stream.edge_stream(stream.event_stream(spark, f"{sf_dir}/events.parquet"))


def stream_edges(spark, sf_dir) -> DataFrame:
    """All edges with their times, as they come."""
    return stream.run_to(_edges(spark, sf_dir), *_place(spark, "edges")).withColumn("ts", F.col("ts").cast("timestamp_ntz"))


def stream_fresh_edges(spark, sf_dir) -> DataFrame:
    return stream.run_to(stream.fresh_edges(_edges(spark, sf_dir), "3650 days"), *_place(spark, "fresh")).select("src", "dst")


def stream_window_support(spark, sf_dir) -> DataFrame:
    return stream.run_to_memory(stream.window_support(_edges(spark, sf_dir), "1 day"), f"w_{uuid4().hex}", "complete").withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


def stream_sliding_support(spark, sf_dir) -> DataFrame:
    return stream.run_to_memory(stream.window_support(_edges(spark, sf_dir), "1 day", "6 hours"), f"w_{uuid4().hex}", "complete").withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


def stream_degrees(spark, sf_dir) -> DataFrame:
    """Last degree of each user.  Typed state needs the RocksDB store, which is set for the run of this stream only."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        out = stream.run_to_memory(stream.degrees(_edges(spark, sf_dir)), f"d_{uuid4().hex}")
    finally:
        spark.conf.set(key, before)
    return out.groupBy("src").agg(F.max("degree").alias("degree"), F.sum("moved").alias("squares"))


def stream_sessions(spark, sf_dir) -> DataFrame:
    """Complete mode gives the sessions that are open at the end as well."""
    return stream.run_to_memory(stream.session_edges(stream.event_stream(spark, f"{sf_dir}/events.parquet"), delay=COVERS), f"s_{uuid4().hex}", "complete")


def stream_two_steps(spark, sf_dir) -> DataFrame:
    """A user to a key, then within ten minutes the key to another user."""
    out, checkpoint = _place(spark, "two")
    stream.return_steps(_edges(spark, sf_dir), out, checkpoint).awaitTermination()
    return spark.read.parquet(f"{out}/steps").select("t1", "t2", "u", "v", "w")


def stream_refresh(spark, sf_dir) -> DataFrame:
    out, checkpoint = _place(spark, "refresh")
    q = stream.refresh_small(_edges(spark, sf_dir), out, checkpoint, 5)
    q.awaitTermination()
    found = spark.read.parquet(f"{out}/support")
    last = found.agg(F.max("version")).first()[0]
    return found.filter(F.col("version") == last).select("pattern_key", F.concat_ws(",", "pins").alias("pins"), "freq")


def _suppliers(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "supplier").selectExpr("s_suppkey as node", "s_nationkey as `group`")


def gen_copy_model(spark, sf_dir) -> DataFrame:
    """Copied links between the suppliers."""
    return copy_model_on(_suppliers(spark, sf_dir).select("node"), 5, 0.1, 7)


def gen_uniform(spark, sf_dir) -> DataFrame:
    """Uniform edges between the suppliers of each nation."""
    return uniform_on(_suppliers(spark, sf_dir), 0.1, 7)


def gen_uniform_native(spark, sf_dir) -> DataFrame:
    return uniform_on_native(_suppliers(spark, sf_dir), 0.1, 7)


_EDGE = "(SELECT ts, 'u:' || user_id AS src, 'k:' || (props->>'$.k') AS dst FROM events) e"
QUERIES = {f.__name__: f for f in (stream_edges, stream_fresh_edges, stream_window_support, stream_sliding_support, stream_degrees, stream_sessions, stream_two_steps, stream_refresh, gen_copy_model, gen_uniform, gen_uniform_native)}
ORACLES = {
    "stream_edges": f"SELECT ts, src, dst FROM {_EDGE}",
    "stream_fresh_edges": f"SELECT DISTINCT src, dst FROM {_EDGE}",
    "stream_window_support": f"SELECT date_trunc('day', ts) AS start, date_trunc('day', ts) + INTERVAL 1 DAY AS \"end\", dst AS pin1, count(DISTINCT src) AS freq FROM {_EDGE} GROUP BY 1, 2, 3",
    "stream_degrees": f"SELECT src, count(DISTINCT dst) AS degree, count(DISTINCT dst) * count(DISTINCT dst) AS squares FROM {_EDGE} GROUP BY src",
}
