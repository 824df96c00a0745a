"""Data graphs on the given tables."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..graph import Graph, load, symmetric

FIRST_DAY = "2024-01-01"
#: Vectors of a block, and cosines that a task holds at once.
BLOCK_VECTORS, AT_ONCE = 16_000, 2_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def named(prefix: str, column: str):
    return F.concat(F.lit(prefix), F.col(column).cast("string"))


def pairs(*parts: DataFrame) -> Graph:
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return load(out.toDF("src", "dst"))


def supply_chain(spark, sf_dir) -> Graph:
    t = lambda x: table(spark, sf_dir, x)
    return pairs(
        t("region").select(F.lit("root"), named("r:", "r_regionkey")), t("nation").select(named("r:", "n_regionkey"), named("n:", "n_nationkey")),
        t("supplier").select(named("n:", "s_nationkey"), named("s:", "s_suppkey")), t("lineitem").select(named("s:", "l_suppkey"), named("p:", "l_partkey")),
        t("part").select(named("p:", "p_partkey"), named("b:", "p_brand")),
    )


def supplier_part(spark, sf_dir) -> Graph:
    return pairs(table(spark, sf_dir, "lineitem").select(named("s:", "l_suppkey"), named("p:", "l_partkey")))


def customer_part(spark, sf_dir) -> Graph:
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    return pairs(o.join(li, o.o_orderkey == li.l_orderkey).select(named("c:", "o_custkey"), named("p:", "l_partkey")))


def order_part(spark, sf_dir) -> Graph:
    return pairs(table(spark, sf_dir, "lineitem").select(named("o:", "l_orderkey"), named("p:", "l_partkey")))


def nation_trade(spark, sf_dir) -> Graph:
    o, li, c, s = (table(spark, sf_dir, x) for x in ("orders", "lineitem", "customer", "supplier"))
    sale = li.join(o, li.l_orderkey == o.o_orderkey).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    return pairs(sale.select(named("n:", "s_nationkey"), named("n:", "c_nationkey")))


def keyed_events(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", F.get_json_object("props", "$.k").cast("bigint").alias("k"))


def user_key(spark, sf_dir) -> Graph:
    return pairs(keyed_events(spark, sf_dir).select(named("u:", "user_id"), named("k:", "k")))


def nearest(m: np.ndarray, w: np.ndarray, k: int, ids: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row of m, row of w and cosine rounded to 6 places, for the k best rows of w for each row of m, ties by row of w; ids: where m is w, rows with one id don't meet.

    Columns fall into groups.  k groups reach the k-th best of the groups' maxima, so only cosines that may round to as much are looked at.
    """
    step, parts = max(1, AT_ONCE // max(1, len(w))), []
    in_group = max(1, min(64, len(w) // (8 * k)))
    whole = len(w) - len(w) % in_group
    for low in range(0, len(m), step):
        cos = m[low : low + step] @ w.T
        if ids is not None:
            cos[ids[low : low + step, None] == ids[None, :]] = -np.inf
        cos[np.isnan(cos)] = -np.inf
        if len(w) > k:
            most = cos[:, :whole].reshape(len(cos), in_group, -1).max(axis=1)
            bound = np.partition(most, -k, axis=1)[:, -k]
            at = np.flatnonzero(cos >= (bound - 2e-6)[:, None])
        else:
            at = np.arange(cos.size)
        value = np.round(cos.ravel()[at], 6)
        at, value = at[np.isfinite(value)], value[np.isfinite(value)]
        row, column = np.divmod(at, len(w))
        order = np.lexsort((column, -value, row))
        row, column, value = row[order], column[order], value[order]
        kept = np.arange(len(row)) - np.searchsorted(row, row) < k
        parts.append((row[kept] + low, column[kept], value[kept]))
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def top_neighbours(vectors: DataFrame, k: int = 5, blocks: int | None = None) -> DataFrame:
    """a, b: for every vector its k nearest others by cosine rounded to 6 places, ties by id.

    Vectors fall into blocks by id; every two blocks meet in a task of their own, as matrices, each as queries on the other, and the best k of each
    meeting are merged.  No task holds more than two blocks, and a vector is sent once for each block.
    """
    n = blocks or max(1, -(-vectors.count() // BLOCK_VECTORS))
    v = vectors.select(F.col("vec_id").alias("id"), "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int").alias("block"))
    other = v.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    sides = other.select("id", "embedding", "block", F.least("block", "other").alias("q"), F.greatest("block", "other").alias("r"))

    def meet(x: pd.DataFrame) -> pd.DataFrame:
        x = x.sort_values("id")
        q, r = x.q.iloc[0], x.r.iloc[0]
        ids, units = {}, {}
        for b in {q, r}:
            mine = x[x.block == b]
            if not len(mine):
                return pd.DataFrame({"a": pd.Series(dtype="int64"), "b": pd.Series(dtype="int64"), "cos": pd.Series(dtype="float64")})
            m = np.stack(mine.embedding.to_numpy()).astype(np.float64)
            ids[b], units[b] = mine.id.to_numpy(), m / np.linalg.norm(m, axis=1, keepdims=True)
        found = []
        for one, two in {(q, r), (r, q)}:
            row, column, cos = nearest(units[one], units[two], k, ids[q] if q == r else None)
            found.append(pd.DataFrame({"a": ids[one][row], "b": ids[two][column], "cos": cos}))
        return pd.concat(found)

    met = sides.groupBy("q", "r").applyInPandas(meet, "a bigint, b bigint, cos double")
    order = Window.partitionBy("a").orderBy(F.desc("cos"), "b")
    return met.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= k).select("a", "b")


def likely_neighbours(vectors: DataFrame, k: int = 5, length: float = 1.0, tables: int = 8, reach: float = 1.0, seed: int = 1) -> DataFrame:
    """a, b as top_neighbours gives, from pairs that share a random-projection bucket and are within reach on the unit sphere: approximate."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH, Normalizer
    from pyspark.ml.functions import array_to_vector

    v = vectors.select(F.col("vec_id").alias("id"), array_to_vector(F.col("embedding").cast("array<double>")).alias("v"))
    unit = Normalizer(inputCol="v", outputCol="u").transform(v).select("id", "u")
    model = BucketedRandomProjectionLSH(inputCol="u", outputCol="h", bucketLength=length, numHashTables=tables, seed=seed).fit(unit)
    met = model.approxSimilarityJoin(unit, unit, reach, "d").select(F.col("datasetA.id").alias("a"), F.col("datasetB.id").alias("b"), F.round(1 - F.col("d") * F.col("d") / 2, 6).alias("cos")).filter("a <> b")
    order = Window.partitionBy("a").orderBy(F.desc("cos"), "b")
    return met.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= k).select("a", "b")


def embedding_neighbors(spark, sf_dir) -> Graph:
    near = top_neighbours(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))
    return symmetric(Graph(near.select(F.col("a").cast("string").alias("src"), F.col("b").cast("string").alias("dst"))))


def key_step(spark, sf_dir, days: int, below: int | None = None) -> Graph:
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    step = keyed_events(spark, sf_dir).withColumn("next_k", F.lead("k").over(order))
    step = step.filter(F.col("ts") < F.expr(f"timestamp'{FIRST_DAY} 00:00:00' + make_interval(0, 0, 0, {days})"))
    if below is not None:
        step = step.filter((F.col("k") < below) & (F.col("next_k") < below))
    return pairs(step.select(F.col("k").cast("string"), F.col("next_k").cast("string")))


def page_path(url: str = "url"):
    return F.regexp_extract(url, r"^https?://[^/]+(/[^?#]*)", 1)


def link_edges(pages: DataFrame) -> DataFrame:
    """Page (path of its url with page number) to the paths of its links."""
    return pages.select(F.concat(F.lit("l:"), F.col("page_id").cast("string")).alias("src"), F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href")).select("src", F.concat(F.lit("l:"), F.col("href")).alias("dst"))


def page_links(spark, sf_dir) -> Graph:
    return pairs(link_edges(table(spark, sf_dir, "pages")))


def site_graph(spark, sf_dir) -> Graph:
    pages = table(spark, sf_dir, "pages")
    host = pages.select(F.concat(F.lit("h:"), F.regexp_extract("url", r"^https?://([^/]+)", 1)), F.concat(F.lit("l:"), F.col("page_id").cast("string")))
    return pairs(link_edges(pages), host)


def doc_attributes(spark, sf_dir) -> Graph:
    d, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    return pairs(d.select(F.col("source"), named("d:", "doc_id")), d.select(named("d:", "doc_id"), named("lang:", "lang")), labels.select(named("d:", "doc_id"), named("quality:", "quality")), labels.select(named("d:", "doc_id"), named("toxic:", "toxic")))


def event_reified(spark, sf_dir) -> Graph:
    e = keyed_events(spark, sf_dir)
    return pairs(e.select(named("u:", "user_id"), named("e:", "event_id")), e.select(named("e:", "event_id"), named("k:", "k")), e.select(named("e:", "event_id"), named("type:", "event_type")))


def word_next(spark, sf_dir) -> Graph:
    words = F.expr("regexp_extract_all(lower(text), '[a-z0-9_]+', 0)")
    rows = table(spark, sf_dir, "conversations").select(F.explode(F.filter(F.arrays_zip(words.alias("a"), F.slice(words, 2, F.greatest(F.size(words), F.lit(1))).alias("b")), lambda x: x["b"].isNotNull())).alias("x"))
    return pairs(rows.select("x.a", "x.b"))


def purchase_tree(spark, sf_dir) -> Graph:
    c, o, li = (table(spark, sf_dir, x) for x in ("customer", "orders", "lineitem"))
    return pairs(c.select(named("n:", "c_nationkey"), named("c:", "c_custkey")), o.select(named("c:", "o_custkey"), named("o:", "o_orderkey")), li.select(named("o:", "l_orderkey"), named("p:", "l_partkey")))


def doc_lines(spark, sf_dir) -> Graph:
    rows = table(spark, sf_dir, "documents").select(named("d:", "doc_id").alias("d"), F.explode(F.split("text", "\n")).alias("line")).filter(F.length("line") >= 40)
    return pairs(rows.select("d", F.md5("line")))


def benchmark_lines(spark, sf_dir) -> Graph:
    """doc_lines with the items of the benchmark as further documents."""
    items = table(spark, sf_dir, "benchmark").select(named("i:", "item_id").alias("d"), F.explode(F.split("text", "\n")).alias("line")).filter(F.length("line") >= 40)
    return pairs(doc_lines(spark, sf_dir).edges, items.select("d", F.md5("line")))


def conv_roles(spark, sf_dir) -> Graph:
    return pairs(table(spark, sf_dir, "conversations").select(named("v:", "conv_id"), F.col("role")))


GRAPHS = {
    "supply_chain": supply_chain, "supplier_part": supplier_part, "customer_part": customer_part, "order_part": order_part, "nation_trade": nation_trade, "user_key": user_key,
    "embedding_neighbors": embedding_neighbors, "key_step_3d": lambda s, d: key_step(s, d, 3), "key_step_3d_51": lambda s, d: key_step(s, d, 3, 51), "key_step_3d_22": lambda s, d: key_step(s, d, 3, 22), "key_step_30d": lambda s, d: key_step(s, d, 30),
    "page_links": page_links, "site_graph": site_graph, "doc_attributes": doc_attributes, "event_reified": event_reified, "word_next": word_next, "purchase_tree": purchase_tree, "doc_lines": doc_lines, "benchmark_lines": benchmark_lines, "conv_roles": conv_roles,
}
