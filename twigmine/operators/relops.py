"""Relational and scalar operations around the methods, one query each, with its SQL."""

from __future__ import annotations

from functools import partial
from inspect import signature

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.udfs import bind_pins, cosine, distinct_at_least, exact_ratio, pattern_key_udf, redundant_udf
from ..graph import with_node_labels
from ..oracles import edge_sql, with_edges
from ..sources.datagraphs import GRAPHS, keyed_events, table
from ..sources.edges import close_pairs, last_before
from ..storage import cut

STEP, WHOLE_STEP = "key_step_3d", "key_step_30d"


def step(spark, sf_dir, g: str = STEP) -> DataFrame:
    return GRAPHS[g](spark, sf_dir).edges


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))


_DEG = "deg AS (SELECT src, count(*) AS deg FROM edge GROUP BY src)"


def rel_projection(s, d, g=STEP):
    e = step(s, d, g)
    return e.select(F.col("dst").alias("parent"), F.col("src").alias("child"), (F.length("src") / F.length("dst")).alias("ratio"))


def rel_filter(s, d, g=STEP):
    return step(s, d, g).filter((F.col("src") == "7") | (F.col("src") == F.col("dst")))


def rel_inner_join(s, d, g=STEP):
    e = step(s, d, g)
    return e.alias("a").join(e.alias("b"), F.col("a.dst") == F.col("b.src")).groupBy(F.col("a.src").alias("src")).agg(F.count(F.lit(1)).alias("paths"))


def rel_left_semi(s, d):
    e = GRAPHS["site_graph"](s, d).edges
    return e.join(e.select(F.col("src").alias("dst")).distinct(), "dst", "left_semi").select("src", "dst")


def rel_left_anti(s, d):
    e = GRAPHS["page_links"](s, d).edges
    return e.select(F.col("src").alias("id")).distinct().join(e.select(F.col("dst").alias("id")), "id", "left_anti")


def rel_outer_join(s, d):
    e = GRAPHS["page_links"](s, d).edges
    out, into = e.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("n_out")), e.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("n_in"))
    return out.join(into, "id", "full")


def rel_cross_join(s, d):
    """Two small tables in all pairs: regions and segments."""
    return table(s, d, "region").select("r_name").crossJoin(table(s, d, "customer").select("c_mktsegment").distinct())


def rel_range_join(s, d):
    return close_pairs(table(s, d, "events"), 3600)


def rel_asof_join(s, d):
    e = table(s, d, "events")
    buys = e.filter("event_type = 'purchase'").select("user_id", "ts", "event_id")
    clicks = e.filter("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return last_before(buys, clicks, "user_id", "ts", "value").select("event_id", F.round("last_value", 6).alias("last_value"))


def rel_self_join(s, d, g="key_step_3d_22"):
    e = step(s, d, g)
    a, b, c = (e.toDF(f"s{k}", f"d{k}") for k in range(3))
    return a.join(b, F.col("d0") == F.col("s1")).join(c, F.col("d1") == F.col("s2")).filter("d2 = s0").select(F.col("s0").alias("x"), F.col("s1").alias("y"), F.col("s2").alias("z"))


def rel_aggregate(s, d, g=STEP):
    return step(s, d, g).groupBy("src").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("dst").alias("different"), F.sum(F.col("dst").cast("bigint")).alias("total"), F.min("dst").alias("least"), F.max("dst").alias("most"))


def rel_grouping_sets(s, d):
    t = table(s, d, "lineitem")
    return t.cube("l_returnflag", "l_linestatus").agg(F.grouping_id("l_returnflag", "l_linestatus").cast("bigint").alias("gid"), F.count(F.lit(1)).alias("n"))


def rel_rollup(s, d):
    return table(s, d, "orders").rollup("o_orderpriority", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def rel_approximate(s, d):
    """A sketch's estimate beside the exact count; only whether they differ by less than a tenth is reported."""
    e = GRAPHS["purchase_tree"](s, d).edges
    return e.agg(F.approx_count_distinct("src", 0.02).alias("a"), F.count_distinct("src").alias("exact")).select("exact", (F.abs(F.col("a") - F.col("exact")) < F.col("exact") * 0.1).alias("near"))


def rel_window(s, d, g=STEP):
    w = Window.orderBy(F.desc("deg"), "src")
    # Spark needs one task to number the whole table: degrees are first cut to the largest 500.
    top = degrees(step(s, d, g)).orderBy(F.desc("deg"), "src").limit(500)
    return top.select("src", "deg", F.row_number().over(w).alias("place"), F.rank().over(Window.orderBy(F.desc("deg"))).alias("rank"), F.dense_rank().over(Window.orderBy(F.desc("deg"))).alias("dense"), F.ntile(4).over(w).alias("quarter"), F.lag("src").over(w).alias("above"), F.sum("deg").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"))


def rel_window_lead(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return keyed_events(s, d).select("event_id", F.lead("k").over(w).alias("next_k"), F.first("k").over(w).alias("first_k"), F.last("k").over(w.rowsBetween(0, Window.unboundedFollowing)).alias("last_k"))


def rel_window_range(s, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-86400, 0)
    return keyed_events(s, d).select("event_id", F.count(F.lit(1)).over(w).alias("day_events"))


def rel_top_k(s, d, g=STEP):
    return degrees(step(s, d, g)).orderBy(F.desc("deg"), "src").limit(10)


def rel_set_ops(s, d):
    a, b = GRAPHS["page_links"](s, d).edges.select(F.col("dst").alias("id")), GRAPHS["page_links"](s, d).edges.select(F.col("src").alias("id"))
    parts = [a.intersect(b), a.exceptAll(b), b.subtract(a), a.union(b)]
    out = None
    for name, p in zip(("intersect", "except_all", "except", "union_all"), parts, strict=True):
        row = p.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("op"), "n")
        out = row if out is None else out.union(row)
    return out


def rel_exists(s, d, g=STEP):
    step(s, d, g).createOrReplaceTempView("rel_edge")
    return s.sql("SELECT DISTINCT e.src FROM rel_edge e WHERE EXISTS (SELECT 1 FROM rel_edge f WHERE f.src = e.dst AND f.dst = '7') AND e.src IN (SELECT dst FROM rel_edge)")


def rel_scalar_subquery(s, d, g=STEP):
    step(s, d, g).createOrReplaceTempView("rel_edge2")
    return s.sql("SELECT dst, count(*) AS freq, round(count(*) / CAST((SELECT count(*) FROM rel_edge2) AS DOUBLE), 6) AS conf FROM rel_edge2 GROUP BY dst")


def rel_pivot(s, d):
    return table(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)


def rel_recursion(s, d):
    """Depths below the root of the supply chain, by recursive SQL: at most six rounds."""
    GRAPHS["supply_chain"](s, d).edges.createOrReplaceTempView("rel_chain")
    return s.sql("WITH RECURSIVE walk(id, depth) AS (SELECT 'root', 0 UNION ALL SELECT DISTINCT e.dst, w.depth + 1 FROM (SELECT DISTINCT id, depth FROM walk) w JOIN rel_chain e ON e.src = w.id WHERE w.depth < 3) SELECT id, min(depth) AS depth FROM walk GROUP BY id")


def rel_recursion_whole(s, d):
    """Depths below the root of the whole supply chain, down to the brands: a round per depth, until no new node appears."""
    e = GRAPHS["supply_chain"](s, d).edges
    seen = reached = cut(s.createDataFrame([("root", 0)], "id string, depth int"), "walk")
    depth = 0
    while True:
        depth += 1
        new = e.join(reached, e.src == reached.id, "left_semi").select(F.col("dst").alias("id")).distinct()
        reached = cut(new.join(seen, "id", "left_anti").select("id", F.lit(depth).alias("depth")), "walk")
        if reached.isEmpty():
            return seen
        seen = seen.union(reached)


def rel_sample(s, d, g=STEP):
    """A preview of a tenth of the edges, by a hash of the row, so it is the same on any partitioning."""
    return step(s, d, g).filter(F.conv(F.substring(F.md5(F.concat("src", F.lit("-"), "dst")), 1, 4), 16, 10).cast("int") < 6554)


def rel_node_labels(s, d):
    links = GRAPHS["page_links"](s, d)
    labels = table(s, d, "pages").select(F.concat(F.lit("l:"), F.col("page_id").cast("string")).alias("id"), F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("label"))
    return with_node_labels(links, labels).edges.filter(F.col("dst").startswith("label:")).groupBy("dst").agg(F.count(F.lit(1)).alias("n"))


def fn_string(s, d):
    t = table(s, d, "documents")
    return t.select("doc_id", F.concat_ws("/", "lang", "source").alias("a"), F.split("text", " ")[0].alias("b"), F.lower(F.substring("text", 1, 20)).alias("c"), F.length("text").cast("bigint").alias("n"), F.md5("text").alias("h"), F.sha2("text", 256).alias("h2"), F.regexp_extract("source", "([0-9]+)", 1).alias("num"))


def fn_date(s, d):
    t = table(s, d, "events")
    return t.select("event_id", F.date_trunc("hour", "ts").cast("string").alias("hour"), F.unix_timestamp("ts").alias("sec"), F.date_format(F.date_add(F.to_date("ts"), 3), "yyyy-MM-dd").alias("later"), F.date_format(F.expr("ts + make_interval(0, 0, 0, 1)"), "yyyy-MM-dd").alias("next"))


def fn_math(s, d):
    t = table(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity", "l_partkey")
    return t.select("l_orderkey", "l_linenumber", F.round(F.sqrt("l_quantity"), 6).alias("root"), F.floor(F.col("l_quantity") / 7).cast("bigint").alias("f"), F.greatest("l_partkey", "l_orderkey").alias("g"), F.pmod(F.col("l_partkey") - 1000, F.lit(7)).cast("bigint").alias("m"))


def fn_array(s, d, g=STEP):
    """Head images: pins taken by a correspondence, and array functions on them."""
    rows = step(s, d, g).select(F.array("src", "dst").alias("pins"), F.array(F.lit(1), F.lit(0), F.lit(1)).alias("rho"))
    rows = rows.select("pins", bind_pins().alias("h"))
    return rows.select(F.concat_ws(",", "pins").alias("pins"), F.concat_ws(",", "h").alias("h"), F.concat_ws(",", F.array_sort(F.array_distinct("h"))).alias("different"), F.exists("pins", lambda x: x == "7").alias("has7"), F.forall("pins", lambda x: F.length(x) == 2).alias("two"), F.aggregate("pins", F.lit(0).cast("bigint"), lambda a, x: a + x.cast("bigint")).alias("total"), F.element_at("h", 3).alias("third"), F.concat_ws(",", F.slice("h", 2, 2)).alias("tail"), F.size(F.flatten(F.array("pins", "h"))).alias("n"))


def fn_map(s, d, g=STEP):
    """Constants by pin name, as a map."""
    m = F.map_from_arrays(F.array(F.lit("a"), F.lit("b")), F.array("src", "dst"))
    rows = step(s, d, g).select("src", "dst", m.alias("m"))
    return rows.select("src", "dst", F.concat_ws(",", F.array_sort(F.map_keys("m"))).alias("keys"), F.transform_values("m", lambda k, v: F.concat(k, v))["b"].alias("named"), F.size(F.map_entries("m")).alias("n"))


def fn_json(s, d):
    t = table(s, d, "events")
    return t.select("event_id", F.get_json_object("props", "$.k").alias("a"), F.from_json("props", "k bigint")["k"].alias("b"), F.expr("variant_get(parse_json(props), '$.k', 'bigint')").alias("c"), F.to_json(F.struct(F.col("event_id").alias("id"))).alias("j"))


def fn_ratio(s, d, g=STEP):
    d1 = degrees(step(s, d, g))
    return d1.crossJoin(F.broadcast(d1.agg(F.sum("deg").alias("lhs_freq")))).select("src", F.round(exact_ratio("deg", "lhs_freq"), 9).cast("double").alias("ratio"))  # one row


def fn_cosine(s, d):
    t = table(s, d, "embeddings").select("vec_id", "embedding")
    a, b = t.filter("vec_id < 20").toDF("a", "x"), t.filter("vec_id < 20").toDF("b", "y")
    return a.join(b, F.col("a") < F.col("b")).select("a", "b", F.round(cosine("x", "y"), 5).alias("cos"))


def fn_cosine_whole(s, d):
    """Every vector with each of the query set (ids divisible by 50)."""
    t = table(s, d, "embeddings").select("vec_id", "embedding")
    a, b = t.filter("vec_id % 50 = 0").toDF("a", "x"), t.toDF("b", "y")
    return b.join(a, F.col("a") != F.col("b")).select("a", "b", F.round(cosine("x", "y"), 5).alias("cos"))


def udf_pattern_key(s, d):
    """Keys of three writings, two of one pattern's tree, beside the events' types and how many events stand for each: from an Arrow function."""
    rows = keyed_events(s, d).groupBy("event_type", (F.col("k") % 3 + 1).alias("id")).agg(F.count(F.lit(1)).alias("n"))
    levels = F.when(F.col("id") == 3, F.lit([0, 1, 1])).when(F.col("id") < 3, F.lit([0, 1, 2, 2, 1, 2, 2]))
    marks = F.when(F.col("id") == 1, "pdddepd").when(F.col("id") == 2, "pepddpd").when(F.col("id") == 3, "dee")
    rows = rows.withColumns({"levels": levels, "marks": marks})
    return rows.select("event_type", "id", "n", pattern_key_udf("levels", "marks").alias("pattern_key"), redundant_udf("levels", "marks").alias("redundant"))


def udf_distinct_at_least(s, d, g=STEP):
    return step(s, d, g).groupBy("src").agg(distinct_at_least(10)("dst").alias("frequent"))


_QUERIES = {
    "rel_projection": (rel_projection, with_edges(STEP, "SELECT dst AS parent, src AS child, length(src) / CAST(length(dst) AS DOUBLE) AS ratio FROM edge")),
    "rel_filter": (rel_filter, with_edges(STEP, "SELECT * FROM edge WHERE src = '7' OR src = dst")),
    "rel_inner_join": (rel_inner_join, with_edges(STEP, "SELECT a.src, count(*) AS paths FROM edge a JOIN edge b ON a.dst = b.src GROUP BY a.src")),
    "rel_left_semi": (rel_left_semi, with_edges("site_graph", "SELECT src, dst FROM edge WHERE dst IN (SELECT src FROM edge)")),
    "rel_left_anti": (rel_left_anti, with_edges("page_links", "SELECT DISTINCT src AS id FROM edge WHERE src NOT IN (SELECT dst FROM edge)")),
    "rel_outer_join": (rel_outer_join, with_edges("page_links", "SELECT coalesce(a.id, b.id) AS id, n_out, n_in FROM (SELECT src AS id, count(*) AS n_out FROM edge GROUP BY src) a FULL JOIN (SELECT dst AS id, count(*) AS n_in FROM edge GROUP BY dst) b ON a.id = b.id")),
    "rel_cross_join": (rel_cross_join, "SELECT r_name, c_mktsegment FROM region, (SELECT DISTINCT c_mktsegment FROM customer) c"),
    "rel_range_join": (rel_range_join, "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND (b.ts > a.ts OR b.ts = a.ts AND b.event_id > a.event_id) AND b.ts <= a.ts + INTERVAL 3600 SECOND"),
    "rel_asof_join": (rel_asof_join, "SELECT b.event_id, round(c.value, 6) AS last_value FROM (SELECT * FROM events WHERE event_type = 'purchase') b ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'click' GROUP BY 1, 2) c ON b.user_id = c.user_id AND b.ts >= c.ts"),
    "rel_self_join": (rel_self_join, with_edges("key_step_3d_22", "SELECT a.src AS x, b.src AS y, c.src AS z FROM edge a JOIN edge b ON a.dst = b.src JOIN edge c ON b.dst = c.src AND c.dst = a.src")),
    "rel_aggregate": (rel_aggregate, with_edges(STEP, "SELECT src, count(*) AS n, count(DISTINCT dst) AS different, CAST(sum(CAST(dst AS BIGINT)) AS BIGINT) AS total, min(dst) AS least, max(dst) AS most FROM edge GROUP BY src")),
    "rel_grouping_sets": (rel_grouping_sets, "SELECT l_returnflag, l_linestatus, CAST(grouping_id(l_returnflag, l_linestatus) AS BIGINT) AS gid, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "rel_rollup": (rel_rollup, "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderpriority, o_orderstatus)"),
    "rel_approximate": (rel_approximate, with_edges("purchase_tree", "SELECT count(DISTINCT src) AS exact, TRUE AS near FROM edge")),
    "rel_window": (rel_window, f"WITH edge AS ({edge_sql(STEP)}), {_DEG}, top AS (SELECT * FROM deg ORDER BY deg DESC, src LIMIT 500) SELECT src, deg, CAST(row_number() OVER w AS INTEGER) AS place, CAST(rank() OVER (ORDER BY deg DESC) AS INTEGER) AS rank, CAST(dense_rank() OVER (ORDER BY deg DESC) AS INTEGER) AS dense, CAST(ntile(4) OVER w AS INTEGER) AS quarter, lag(src) OVER w AS above, CAST(sum(deg) OVER (ORDER BY deg DESC, src ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM top WINDOW w AS (ORDER BY deg DESC, src)"),
    "rel_window_lead": (rel_window_lead, "SELECT event_id, lead(k) OVER w AS next_k, first(k) OVER w AS first_k, last(k) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS last_k FROM (SELECT event_id, ts, user_id, CAST(props->>'$.k' AS BIGINT) AS k FROM events) q WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "rel_window_range": (rel_window_range, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day_events FROM events"),
    "rel_top_k": (rel_top_k, f"WITH edge AS ({edge_sql(STEP)}), {_DEG} SELECT src, deg FROM deg ORDER BY deg DESC, src LIMIT 10"),
    "rel_set_ops": (rel_set_ops, with_edges("page_links", "SELECT 'intersect' AS op, (SELECT count(*) FROM (SELECT dst FROM edge INTERSECT SELECT src FROM edge) a) AS n UNION ALL SELECT 'except_all', (SELECT count(*) FROM (SELECT dst FROM edge EXCEPT ALL SELECT src FROM edge) a) UNION ALL SELECT 'except', (SELECT count(*) FROM (SELECT src FROM edge EXCEPT SELECT dst FROM edge) a) UNION ALL SELECT 'union_all', (SELECT 2 * count(*) FROM edge)")),
    "rel_exists": (rel_exists, with_edges(STEP, "SELECT DISTINCT e.src FROM edge e WHERE e.dst IN (SELECT src FROM edge WHERE dst = '7') AND e.src IN (SELECT dst FROM edge)")),
    "rel_scalar_subquery": (rel_scalar_subquery, with_edges(STEP, "SELECT dst, count(*) AS freq, round(count(*) / CAST((SELECT count(*) FROM edge) AS DOUBLE), 6) AS conf FROM edge GROUP BY dst")),
    "rel_pivot": (rel_pivot, "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY o_orderpriority"),
    "rel_recursion": (rel_recursion, "SELECT 'root' AS id, 0 AS depth UNION ALL SELECT DISTINCT 'r:' || r_regionkey, 1 FROM region UNION ALL SELECT DISTINCT 'n:' || n_nationkey, 2 FROM nation UNION ALL SELECT DISTINCT 's:' || s_suppkey, 3 FROM supplier"),
    "rel_sample": (rel_sample, with_edges(STEP, "SELECT * FROM edge WHERE CAST('0x' || substr(md5(src || '-' || dst), 1, 4) AS INTEGER) < 6554")),
    "rel_node_labels": (rel_node_labels, "SELECT 'label:' || regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS dst, count(*) AS n FROM pages WHERE html IS NOT NULL GROUP BY 1"),
    "fn_string": (fn_string, "SELECT doc_id, concat_ws('/', lang, source) AS a, string_split(text, ' ')[1] AS b, lower(substr(text, 1, 20)) AS c, CAST(length(text) AS BIGINT) AS n, md5(text) AS h, sha256(text) AS h2, regexp_extract(source, '([0-9]+)', 1) AS num FROM documents"),
    "fn_date": (fn_date, "SELECT event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS hour, CAST(floor(epoch(ts)) AS BIGINT) AS sec, strftime(CAST(ts AS DATE) + 3, '%Y-%m-%d') AS later, strftime(ts + INTERVAL 1 DAY, '%Y-%m-%d') AS next FROM events"),
    "fn_math": (fn_math, "SELECT l_orderkey, l_linenumber, round(sqrt(l_quantity), 6) AS root, CAST(floor(l_quantity / 7) AS BIGINT) AS f, greatest(l_partkey, l_orderkey) AS g, CAST(((l_partkey - 1000) % 7 + 7) % 7 AS BIGINT) AS m FROM lineitem"),
    "fn_array": (fn_array, with_edges(STEP, "SELECT src || ',' || dst AS pins, dst || ',' || src || ',' || dst AS h, CASE WHEN src = dst THEN src ELSE least(src, dst) || ',' || greatest(src, dst) END AS different, src = '7' OR dst = '7' AS has7, length(src) = 2 AND length(dst) = 2 AS two, CAST(src AS BIGINT) + CAST(dst AS BIGINT) AS total, dst AS third, src || ',' || dst AS tail, 5 AS n FROM edge")),
    "fn_map": (fn_map, with_edges(STEP, "SELECT src, dst, 'a,b' AS keys, 'b' || dst AS named, 2 AS n FROM edge")),
    "fn_json": (fn_json, "SELECT event_id, props->>'$.k' AS a, CAST(props->>'$.k' AS BIGINT) AS b, CAST(props->>'$.k' AS BIGINT) AS c, '{\"id\":' || event_id || '}' AS j FROM events"),
    "fn_ratio": (fn_ratio, f"WITH edge AS ({edge_sql(STEP)}), {_DEG} SELECT src, round(deg / CAST((SELECT sum(deg) FROM deg) AS DOUBLE), 9) AS ratio FROM deg"),
    "fn_cosine": (fn_cosine, "SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 5) AS cos FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE a.vec_id < 20 AND b.vec_id < 20"),
    "udf_pattern_key": (udf_pattern_key, "SELECT event_type, id, n, CASE id WHEN 1 THEN '0p1e2p2d1d2d2d' WHEN 2 THEN '0p1e2p2d1d2p2d' WHEN 3 THEN '0d1e1e' END AS pattern_key, id = 3 AS redundant FROM (SELECT event_type, CAST(props->>'$.k' AS BIGINT) % 3 + 1 AS id, count(*) AS n FROM events GROUP BY 1, 2) q"),
    "udf_distinct_at_least": (udf_distinct_at_least, with_edges(STEP, "SELECT src, count(*) >= 10 AS frequent FROM edge GROUP BY src")),
}

QUERIES = {k: q for k, (q, _) in _QUERIES.items()}
ORACLES = {k: sql for k, (_, sql) in _QUERIES.items() if sql}

QUERIES["fn_cosine_whole"] = fn_cosine_whole
ORACLES["fn_cosine_whole"] = "SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 5) AS cos FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0"
QUERIES["rel_recursion_whole"] = rel_recursion_whole
ORACLES["rel_recursion_whole"] = _QUERIES["rel_recursion"][1] + " UNION ALL SELECT DISTINCT 'p:' || l_partkey, 4 FROM lineitem UNION ALL SELECT DISTINCT 'b:' || p_brand, 5 FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem)"

#: The queries on parts of the step graph, on the whole of it.
for _name, (_f, _sql) in _QUERIES.items():
    if "g" in signature(_f).parameters:
        QUERIES[f"{_name}_whole"] = partial(_f, g=WHOLE_STEP)
        ORACLES[f"{_name}_whole"] = _sql.replace(edge_sql(signature(_f).parameters["g"].default), edge_sql(WHOLE_STEP))
