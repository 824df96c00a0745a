"""Readers, generators, streams and SQL functions."""

from pyspark.sql import functions as F

from twigmine.functions.udfs import register as register_functions
from twigmine.graph import load
from twigmine.model.query import parse_pattern
from twigmine.operators.miner import brute_force
from twigmine.plans.twig import support_table
from twigmine.sources.edges import close_pairs, edges_from, last_before, read_edges, register_views
from twigmine.sources.synthetic import CopyModelReader, register, uniform_edges
from twigmine.streaming import queries as streams
from twigmine.streaming import stream


def test_formats(spark, tmp_path):
    rows = spark.createDataFrame([("a", "b"), ("b", "c"), ("b", "c")], "src string, dst string")
    for fmt in ("parquet", "csv", "json", "orc"):
        rows.write.format(fmt).save(str(tmp_path / fmt))
        assert read_edges(spark, fmt, str(tmp_path / fmt)).edges.count() == 2
    rows.select(F.concat_ws(" ", "src", "dst")).write.text(str(tmp_path / "text"))
    assert sorted(map(tuple, read_edges(spark, "text", str(tmp_path / "text")).edges.collect())) == [("a", "b"), ("b", "c")]


def test_edges_from_columns(spark):
    df = spark.createDataFrame([(1, 2.5), (1, None)], "a int, b double")
    assert [tuple(r) for r in edges_from(df, "a", "b", "x:", "y:").edges.collect()] == [("x:1", "y:2.5")]


def test_views(spark):
    g = load(spark.createDataFrame([(1, 2), (2, 3)], "src bigint, dst bigint"))
    register_views(g)
    assert spark.sql("SELECT count(*) FROM edge JOIN nodes ON src = id").first()[0] == 2


def test_time_joins(spark):
    e = spark.createDataFrame([(1, 1, "2024-01-01 00:00:00", 1.0), (2, 1, "2024-01-01 00:00:50", 2.0), (3, 1, "2024-01-01 00:02:00", 3.0), (4, 2, "2024-01-01 00:00:10", 4.0)], "event_id bigint, user_id bigint, t string, value double").withColumn("ts", F.to_timestamp("t"))
    assert [tuple(r) for r in close_pairs(e, 60).collect()] == [(1, 2)]
    left, right = e.filter("event_id >= 2").drop("value", "t"), e.filter("event_id < 2").drop("t")
    assert {r.event_id: r.last_value for r in last_before(left, right, "user_id", "ts", "value").collect()} == {2: 1.0, 3: 1.0, 4: None}


def test_generators(spark):
    register(spark)
    g = spark.read.format("copy_model").options(nodes=200, degree=5, seed=3, parts=4).load()
    same = spark.read.format("copy_model").options(nodes=200, degree=5, seed=3, parts=1).load()
    assert g.exceptAll(same).count() == 0 and same.count() == g.count() > 400
    assert g.filter("dst >= src").count() == 0
    assert CopyModelReader({"nodes": 50, "p_random": 1.0}).link(40, 0) < 40
    u = spark.read.format("uniform_graph").options(nodes=60, p=0.1, seed=1).load().count()
    assert 250 < u < 470 and 250 < uniform_edges(spark, 60, 0.1, 1).count() < 470


def test_sql_functions(spark):
    register_functions(spark)
    edges = [(0, 1), (0, 2), (0, 3), (1, 4), (2, 4), (2, 5), (3, 6)]
    spark.createDataFrame([(str(a), str(b)) for a, b in edges], "src string, dst string").createOrReplaceTempView("small_edges")
    found = spark.sql("SELECT * FROM mine_tree_patterns(TABLE(small_edges) WITH SINGLE PARTITION, 3, 3)")
    g = load(spark.table("small_edges"))
    want = sorted((r.pattern_key, tuple(r.pins), r.freq) for r in brute_force(g, 3, 3).collect())
    assert sorted((r.pattern_key, tuple(r.pins), r.freq) for r in found.collect()) == want
    made = spark.sql("SELECT count(*), count_if(legal) FROM fold_maps('0d1p1d1d', '0d1p1d')").first()
    assert tuple(made) == (4, 3)
    assert spark.sql("SELECT pattern_key(array(0, 1, 1), 'ddp')").first()[0] == "0d1p1d"


def test_streams_are_batches(spark, sf):
    batch = spark.read.parquet(f"{sf}/events.parquet").select(F.concat(F.lit("u:"), F.col("user_id").cast("string")).alias("src"), F.concat(F.lit("k:"), F.get_json_object("props", "$.k")).alias("dst"), "ts")
    assert streams.stream_fresh_edges(spark, sf).exceptAll(batch.select("src", "dst").distinct()).count() == 0
    w = batch.groupBy(F.window("ts", "1 day").alias("w"), "dst").agg(F.count_distinct("src").alias("freq"))
    got = streams.stream_window_support(spark, sf)
    assert got.count() == w.count() and got.agg(F.sum("freq")).first()[0] == w.agg(F.sum("freq")).first()[0]
    d = batch.select("src", "dst").distinct().groupBy("src").count()
    last = {r.src: (r.degree, r.squares) for r in streams.stream_degrees(spark, sf).collect()}
    assert last == {r.src: (r["count"], r["count"] ** 2) for r in d.collect()}


def test_refreshed_tables(spark, sf, tmp_path):
    edges = stream.edge_stream(stream.event_stream(spark, f"{sf}/events.parquet"))
    stream.refresh_small(edges, str(tmp_path / "r"), str(tmp_path / "c"), 3).awaitTermination()
    found = spark.read.parquet(str(tmp_path / "r/support"))
    g = load(spark.read.parquet(str(tmp_path / "r/edges")))
    p = parse_pattern("x(#a)").pattern
    assert found.filter("pattern_key = '0d1p'").count() == support_table(g, p, minsup=3).count()


def test_likely_neighbours(spark):
    from twigmine.sources.datagraphs import likely_neighbours, top_neighbours

    v = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet").select("vec_id", "embedding")
    exact = {tuple(r) for r in top_neighbours(v, 5, blocks=3).collect()}
    assert exact == {tuple(r) for r in top_neighbours(v, 5).collect()}
    found = {tuple(r) for r in likely_neighbours(v, 5, length=0.5, tables=16, reach=1.4).collect()}
    assert len(exact & found) >= 0.9 * len(exact)


def test_slow_log_and_shares(spark):
    from twigmine.operators.browse import shares
    from twigmine.operators.miner import mine
    from twigmine.operators.slowlog import slow_log

    g = load(spark.createDataFrame([(1, 2), (1, 3), (2, 3)], "src bigint, dst bigint"))
    rows = slow_log(g, [parse_pattern("x(y)").pattern, parse_pattern("x(#a)").pattern]).collect()
    assert {(r.pattern_key, r.n_rows, r.total) for r in rows} == {("0d1d", 1, 3), ("0d1p", 2, 3)}
    assert shares(mine(g, 3, 1).tables, g).first().share == 1.0


def test_queries_on_parts_have_one_on_the_whole(spark, sf):
    import duckdb

    from twigmine.queries import ORACLES, QUERIES

    for name, sql in ORACLES.items():
        cut = "INTERVAL 3 DAY" in sql
        whole = name.startswith(("g_", "stats_", "freq_level", "rule_sparsity", "rule_edge_share", "sup_")) or f"{name}_whole" in QUERIES
        assert not cut or whole, name
    db = duckdb.connect()
    db.execute(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    for name in ("rel_self_join_whole", "match_hub_whole", "rel_top_k_whole"):
        assert sorted(map(tuple, QUERIES[name](spark, sf).collect())) == sorted(db.execute(ORACLES[name]).fetchall())


def test_recursion_reaches_the_brands(spark, sf):
    import duckdb

    from twigmine.queries import ORACLES, QUERIES

    db = duckdb.connect()
    for t in ("region", "nation", "supplier", "lineitem", "part"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = sorted(map(tuple, QUERIES["rel_recursion_whole"](spark, sf).collect()))
    assert got == sorted(db.execute(ORACLES["rel_recursion_whole"]).fetchall()) and max(d for _, d in got) == 5


def test_streams_of_unordered_files_give_the_batch(spark, tmp_path):
    day = [(1, 1, "10:00:00", 1), (2, 1, "10:05:00", 2), (3, 1, "10:08:00", 3), (4, 2, "09:00:00", 1), (5, 2, "09:09:00", 1), (6, 1, "01:00:00", 3), (7, 3, "01:04:00", 3), (8, 1, "01:09:00", 4)]
    rows = spark.createDataFrame([(i, u, f"2024-01-02 {t}", "click", f'{{"k": {k}}}') for i, u, t, k in day], "event_id bigint, user_id bigint, t string, event_type string, props string").withColumn("ts", F.to_timestamp("t").cast("timestamp_ntz")).drop("t")
    for ids in ((1, 2, 3), (4, 5), (6, 7, 8)):
        rows.filter(F.col("event_id").isin(*ids)).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    got = [(r.user_id, r.src, r.dst) for r in streams.stream_sessions(spark, str(tmp_path)).collect()]
    assert sorted(got) == [(1, "1", "2"), (1, "2", "3"), (1, "3", "4"), (2, "1", "1")]
    steps = sorted((r.u, r.v, r.w) for r in streams.stream_two_steps(spark, str(tmp_path)).collect())
    assert steps == [("u:1", "k:3", "u:3")]


def test_cosine_reads_every_vector(spark, sf):
    from twigmine.queries import QUERIES

    ids = {r.vec_id for r in spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id").collect()}
    got = QUERIES["fn_cosine_whole"](spark, sf).collect()
    assert {r.b for r in got} == ids and len(got) == sum(i % 50 == 0 for i in ids) * (len(ids) - 1)


def test_fold_maps_are_of_patterns_in_the_table(spark, sf):
    from twigmine.model.contain import fold_maps
    from twigmine.model.pattern import pattern_of_key
    from twigmine.queries import QUERIES, RULE_LHS, WHOLE, WHOLE_MINSUP, _store

    df = QUERIES["fold_maps_count"](spark, sf)
    keys = {r[0] for r in _store(spark, sf, WHOLE, WHOLE_MINSUP).support.select("pattern_key").distinct().collect()}
    made = {k: sum(1 for _ in fold_maps(RULE_LHS.body, pattern_of_key(k))) for k in keys}
    assert df.inputFiles() and {r.rhs_key: r.made for r in df.collect()} == {k: c for k, c in made.items() if c} != {}


def test_two_steps_meet_by_slots_of_time(spark, tmp_path):
    """Every pair of the definition once, over several files; a node's edges of other times are never compared, and no state is kept."""
    import random
    from datetime import datetime, timedelta

    r, start = random.Random(5), datetime(2024, 1, 2)
    day = [(i, r.randrange(6), start + timedelta(seconds=r.randrange(40) * 150), r.randrange(3)) for i in range(120)]
    rows = spark.createDataFrame([(i, u, t, f'{{"k": {k}}}') for i, u, t, k in day], "event_id bigint, user_id bigint, ts timestamp_ntz, props string")
    for part in range(3):
        rows.filter(F.col("event_id") % 3 == part).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    want = sorted((f"u:{u}", f"k:{k}", f"u:{w}", str(t), str(t2)) for _, u, t, k in day for _, w, t2, k2 in day if k == k2 and u != w and timedelta(0) <= t2 - t <= timedelta(minutes=10))
    found = streams.stream_two_steps(spark, str(tmp_path))
    assert want and sorted((x.u, x.v, x.w, str(x.t1), str(x.t2)) for x in found.collect()) == want
    place = spark.conf.get("spark.checkpoint.dir")
    from pathlib import Path

    assert not list(Path(place.removeprefix("file:")).glob("two-*/checkpoint/state"))


def test_generated_graphs_stand_on_suppliers(spark, sf):
    nation = {r.s_suppkey: r.s_nationkey for r in spark.read.parquet("/root/testdata/sf0.01/supplier.parquet").collect()}
    copied = sorted(map(tuple, streams.gen_copy_model(spark, "/root/testdata/sf0.01").collect()))
    model = CopyModelReader({"degree": 5, "p_random": 0.1, "seed": 7})
    assert copied == sorted((v, dst) for v in nation if v > 0 for dst in {model.link(v, k) for k in range(5)})
    pairs = sum(a == b for a in nation.values() for b in nation.values())
    for made in (streams.gen_uniform, streams.gen_uniform_native):
        df = made(spark, "/root/testdata/sf0.01")
        got = [tuple(r) for r in df.repartition(3).collect()]
        assert len(got) == len(set(got)) and all(nation[a] == nation[b] for a, b in got) and 0 < len(got) < pairs / 4
        assert df.inputFiles()


def test_keys_and_repeats_are_of_the_tables(spark, sf):
    import duckdb

    from twigmine.queries import ORACLES, QUERIES

    db = duckdb.connect()
    db.execute(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    found = QUERIES["udf_pattern_key"](spark, sf)
    assert found.inputFiles() and sorted(map(tuple, found.collect())) == sorted(db.execute(ORACLES["udf_pattern_key"]).fetchall())
    made = {r.dedup: r for r in QUERIES["rule_dedup_counts"](spark, sf).collect()}
    assert made["none"].made == made["complete"].made >= made["none"].legal >= made["linear"].kept >= made["complete"].kept > 0


def test_nearest_of_many_columns_are_those_of_a_whole_sort(spark):
    import numpy as np

    from twigmine.sources.datagraphs import nearest, top_neighbours

    draw = np.random.default_rng(3)
    v = draw.integers(-2, 3, (900, 4)).astype(np.float64)  # many equal directions, and some without any
    v = np.concatenate([v, draw.normal(size=(300, 4))])[draw.permutation(1200)]
    with np.errstate(invalid="ignore"):
        u = v / np.linalg.norm(v, axis=1, keepdims=True)
    ids = np.sort(np.r_[np.arange(1190), np.arange(10)])  # ten ids twice
    cos = np.round(u @ u.T, 6)
    cos[ids[:, None] == ids[None, :]] = -np.inf
    cos[np.isnan(cos)] = -np.inf
    order = np.argsort(-cos, axis=1, kind="stable")[:, :5]
    expected = {(a, int(b)) for a in range(1200) for b in order[a] if np.isfinite(cos[a, b])}
    row, column, _ = nearest(u, u, 5, ids)
    assert set(zip(row.tolist(), column.tolist(), strict=True)) == expected and len(row) == len(expected)
    # The same through Spark, in one block and in four.
    table = spark.createDataFrame([(k, x.tolist()) for k, x in enumerate(v)], "vec_id bigint, embedding array<float>")
    one, four = ({tuple(r) for r in top_neighbours(table, 5, n).collect()} for n in (1, 4))
    assert one == four
    sent = top_neighbours(table, 5, 4)._jdf.queryExecution().optimizedPlan().toString()
    assert sent.count("Generate explode") == 1  # a vector goes once to each block, not once for each side
