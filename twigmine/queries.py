"""All queries over the given tables, each with its SQL where SQL can say it."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .graph import Graph, edge_share, extension_share, load, node_share, sparsity_confidence, stats
from .model.contain import fold_maps
from .model.pattern import Pattern, all_marks, pattern_of_key
from .model.query import TreeQuery, parse_pattern, pure, to_sql
from .model.shape import shapes
from .operators import browse, relops, rules
from .operators.catalog import Catalog, Tables, diff
from .operators.miner import Budget, candidates, flock, mine, mine_tree
from .oracles import edge_sql, rules_sql, tall_sql, with_edges
from .plans.twig import answer_set, matchings, n, support_table
from .sources.datagraphs import GRAPHS
from .streaming import queries as stream_queries

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def graph(name: str, spark: SparkSession, sf_dir: str) -> Graph:
    return GRAPHS[name](spark, sf_dir)


def kept(name: str, spark: SparkSession, sf_dir: str) -> Graph:
    """A graph that many queries of one search read: written once, and nothing stays in memory after the query."""
    return graph(name, spark, sf_dir).stored()


def add(name: str, run: Query, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def numbered(df: DataFrame, p: Pattern, constants: dict | None = None) -> DataFrame:
    pins = [i for i in p.pins if i not in (constants or {})]
    return df.select(*[F.col(n(i)).alias(f"pin{k}") for k, i in enumerate(pins, 1)], "freq")


def padded(df: DataFrame, most: int, *before: str) -> DataFrame:
    """An array of pins as pin1..pinK, null padded."""
    return df.select(*before, *[F.get("pins", F.lit(k)).cast("string").alias(f"pin{k + 1}") for k in range(most)], "freq")


def conf(df: DataFrame) -> DataFrame:
    return df.withColumn("conf", F.round(F.col("freq").cast("double") / F.col("lhs_freq"), 6))


# Edges and measures of every graph.
for _g in GRAPHS:
    add(f"g_{_g}", lambda s, d, g=_g: graph(g, s, d).edges, edge_sql(_g))
    add(
        f"stats_{_g}", lambda s, d, g=_g: stats(graph(g, s, d)),
        with_edges(_g, "SELECT CAST((SELECT count(*) FROM edge) AS BIGINT) AS n_edges, CAST((SELECT count(*) FROM (SELECT src FROM edge UNION SELECT dst FROM edge) q) AS BIGINT) AS n_nodes, CAST(sum(c * c) AS BIGINT) AS sum_out2, CAST(max(c) AS BIGINT) AS max_out, (SELECT CAST(max(c) AS BIGINT) FROM (SELECT count(*) AS c FROM edge GROUP BY dst) i) AS max_in FROM (SELECT count(*) AS c FROM edge GROUP BY src) o"),
    )


def add_support(name: str, g: str, text: str, minsup: int | None = None, prune: bool = False, where: str = "", strategy: str = "fold") -> None:
    """A support table; prune: pins may only take values frequent by themselves, as the search does."""
    named = parse_pattern(text)
    p = named.pattern

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        data = (kept if strategy == "blocks" else graph)(g, spark, sf_dir)
        allowed = None
        # Blocks leave out by themselves what is not frequent alone.
        if prune and strategy != "blocks":
            alone = {i: Pattern(p.levels, "".join("d" if m == "p" and j != i else m for j, m in enumerate(p.marks))) for i in p.pins}
            allowed = {i: support_table(data, q, minsup=minsup).select(n(i)) for i, q in alone.items()}
        out = numbered(support_table(data, p, named.constants, minsup or 1, strategy, allowed), p, named.constants)
        return out.filter(where) if where else out

    sql = to_sql(p, named.constants, minsup=minsup)
    add(name, run, with_edges(g, f"SELECT * FROM ({sql}) w WHERE {where or 'freq > 0'}"))


add_support("match_chain4", "supply_chain", "x(?(?(?(#c))))")
add_support("sup_competitor", "supply_chain", "#n(?(#p=p:8, x))")
add_support("sup_repeated_pin", "key_step_3d", "?(x1(?(#c, x2)), #d)", where="pin1 = pin2")
add_support("sup_pair", "customer_part", "x1(#a, #b)", minsup=5, prune=True, where="pin1 < pin2")
add_support("sup_pair_star", "supplier_part", "x1(#a, #b)", minsup=18, prune=True, where="pin1 < pin2", strategy="blocks")
add_support("sup_pair_lines", "benchmark_lines", "x1(#a, #b)", minsup=3, prune=True, where="pin1 < pin2")
add_support("sup_single", "page_links", "x")
add_support("sup_edge", "page_links", "x(y)")
add_support("sup_fork", "page_links", "x(y, z)")
add_support("sup_hidden_root", "page_links", "?(x, y)")
add_support("sup_hidden_leaf", "page_links", "x(?, y)")
add_support("sup_pinned_root", "page_links", "#r(x, y)")
add_support("sup_pins2", "page_links", "x(#a, #b)", minsup=2)
add_support("sup_hidden_chain", "key_step_30d", "#a(?(?(x)))")
add_support("sup_six_nodes", "key_step_3d", "x1(x2(x3), x4(x5, x6))")
add_support("sup_probe_words", "word_next", "#a(x)", minsup=100)


def _matchings(g: str, text: str) -> tuple[Query, str]:
    p = parse_pattern(text).pattern
    node = {0: "e1.src"} | {i: f"e{i}.dst" for i in range(1, p.size)}
    source = ", ".join(f"edge e{i}" for i in range(1, p.size))
    on = " AND ".join(f"e{i}.src = {node[p.parent[i]]}" for i in range(2, p.size))
    return lambda s, d: matchings(graph(g, s, d), p), with_edges(g, f"SELECT {', '.join(f'{v} AS n{i}' for i, v in node.items())} FROM {source} WHERE {on}")


add("match_fork", *_matchings("key_step_3d_22", "x(y, z)"))
add("match_path", *_matchings("key_step_3d_22", "x(y(z))"))
add(
    "match_hub", lambda s, d: answer_set(graph("key_step_3d_22", s, d), (0, 2, 0), parse_pattern("#a(?(x))").pattern),
    with_edges("key_step_3d_22", "SELECT DISTINCT e1.src AS h1, e2.dst AS h2, e1.src AS h3 FROM edge e1 JOIN edge e2 ON e2.src = e1.dst"),
)
add(
    "answer_impure_head", lambda s, d: answer_set(graph("page_links", s, d), (0, 1, 1, 0), parse_pattern("x(#a)").pattern),
    with_edges("page_links", "SELECT DISTINCT src AS h1, dst AS h2, dst AS h3, src AS h4 FROM edge"),
)

SHAPES3 = [t for t in shapes(3) if len(t) == 3]


def _candidates(text: str, minsup: int, graph_name: str = "key_step_3d_22") -> tuple[Query, str]:
    """Candidate assignments of a pattern against the SQL join of its parents' full support tables."""
    p = parse_pattern(text).pattern
    assert p.is_canonical()

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = kept(graph_name, spark, sf_dir)
        found = mine_tree(g, p.levels, minsup)
        out = candidates(p, Tables(found), g)
        return out.select(*[F.col(n(i)).alias(f"pin{k}") for k, i in enumerate(p.pins, 1)])

    conditions = []
    for q in p.parents():
        on = " AND ".join(f"t.pin{q.pins.index(i) + 1} = c{k}.id" for k, i in enumerate(p.pins, 1) if i in q.pins) or "TRUE"
        conditions.append(f"EXISTS (SELECT 1 FROM ({to_sql(q, minsup=minsup)}) t WHERE {on} AND t.freq >= {minsup})")
    nodes = "(SELECT src AS id FROM edge UNION SELECT dst FROM edge)"
    source = ", ".join(f"{nodes} c{k}" for k in range(1, len(p.pins) + 1))
    columns = ", ".join(f"c{k}.id AS pin{k}" for k in range(1, len(p.pins) + 1))
    return run, with_edges(graph_name, f"SELECT DISTINCT {columns} FROM {source} WHERE {' AND '.join(conditions)}")


add("cand_join_level1", *_candidates("x(y, z)".replace("y", "#a"), 10))
add("cand_join_level2", *_candidates("#r(#a, z)", 10))
add("cand_join_level3", *_candidates("#r(#a, ?)", 4) if parse_pattern("#r(#a, ?)").pattern.is_canonical() and not parse_pattern("#r(#a, ?)").pattern.has_redundancy() else _candidates("?(#a, #b)", 4))


def _level(g: str, level: int, minsup: int) -> tuple[Query, str]:
    patterns = [p for t in SHAPES3 for p in all_marks(t, "full") if p.level == level]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        data = kept(g, spark, sf_dir)
        out = None
        for t in SHAPES3:
            found = mine_tree(data, t, minsup)
            out = found if out is None else out.unionByName(found)
        return padded(out.filter(F.col("level") == level), 3, "pattern_key")

    return run, with_edges(g, tall_sql(patterns, minsup, 3))


for _k in range(4):
    # Without a free node a pattern has support 1 where it matches.
    add(f"freq_level{_k}_key_step_3d_22", *_level("key_step_3d_22", _k, 10 if _k < 3 else 1))
    add(f"freq_level{_k}_page_links", *_level("page_links", _k, 10 if _k < 3 else 1))


def _mined(g: str, minsup: int, size: int, **how) -> tuple[Query, str]:
    patterns = [p for t in shapes(size, how.get("min_height", 0)) for p in all_marks(t, "full")]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = mine(kept(g, spark, sf_dir), minsup, size, **how).tables.support
        if how.get("dedup") in ("none", "redundancy", "canonical"):
            from .operators.miner import reduced_rows

            found = reduced_rows(found)
        return padded(found, size, "pattern_key")

    return run, with_edges(g, tall_sql(patterns, minsup, size))


add("mine_v1_size3", *_mined("key_step_3d_22", 10, 3, dedup="none", order="double"))
add("mine_v2_size3", *_mined("page_links", 5, 3))
add("mine_v2_size4", *_mined("key_step_3d_22", 25, 4, min_height=2))
add("mine_cube_size3", *_mined("page_links", 10, 3, strategy="cube"))
add("mine_cube_size4", *_mined("key_step_3d_22", 10, 4, strategy="cube"))
add("mine_no_copies_size3", *_mined("key_step_3d_22", 10, 3, dedup="canonical"))
add("mine_no_redundancy_size3", *_mined("key_step_3d_22", 10, 3, dedup="redundancy"))
add("mine_expand_size3", *_mined("key_step_3d_51", 25, 3, strategy="expand"))

_flock = parse_pattern("#r(#a, ?(z))").pattern
_flock_all = sorted({p.canonize()[0] for marks in ("ddde", "pdde", "dpde", "ppde") for p in [Pattern(_flock.levels, "".join({"0": marks[0], "1": marks[1]}.get(str(i), _flock.marks[i]) for i in range(4)))]}, key=lambda p: p.marks)
add("flock_fork", lambda s, d: padded(flock(kept("site_graph", s, d), _flock, 5).tables.support, 2, "pattern_key"), with_edges("site_graph", tall_sql(_flock_all, 5, 2)))


def complete_graph_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    """On the complete trade graph a pattern with constants has 25 to the number of its free nodes answers: the range of supports per pattern."""
    g = kept("nation_trade", spark, sf_dir)
    out = None
    for t in shapes(3):
        for p in all_marks(t, "full"):
            row = support_table(g, p).agg(F.min("freq").alias("least"), F.max("freq").alias("most")).select(F.lit(p.refined()).alias("pattern_key"), F.lit(len(p.free)).alias("n_free"), "least", "most")
            out = row if out is None else out.unionByName(row)
    return out


add("complete_graph_law", complete_graph_law, " UNION ALL ".join(f"SELECT '{p.refined()}' AS pattern_key, {len(p.free)} AS n_free, CAST(25 ** {len(p.free)} AS BIGINT) AS least, CAST(25 ** {len(p.free)} AS BIGINT) AS most" for t in shapes(3) for p in all_marks(t, "full")))


def add_rule(name: str, g: str, lhs: str, rhs: str, minsup: int | None = None) -> None:
    """A single rule whose lhs has no pins: pins of rhs, freq, lhs_freq, conf."""
    left, right = parse_pattern(lhs), parse_pattern(rhs)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return conf(rules.ratio(graph(g, spark, sf_dir), left.pattern, right.pattern, right.constants).filter(F.col("freq") >= (minsup or 1)))

    sql = f"SELECT r.*, l.freq AS lhs_freq, round(CAST(r.freq AS DOUBLE) / l.freq, 6) AS conf FROM ({to_sql(right.pattern, right.constants, minsup=minsup)}) r, ({to_sql(left.pattern)}) l WHERE r.freq > 0"
    add(name, run, with_edges(g, sql))


add_rule("rule_cofriend", "embedding_neighbors", "?(x1, x2)", "?(x1, #c)")
add_rule("rule_depth_root", "supply_chain", "x1(x2(x3(x4(x5))))", "#c(x2(x3(x4(x5))))")
add_rule("rule_depth_below", "supply_chain", "x1(x2(x3(x4(x5))))", "#c=root(x1(x2(x3(x4(x5)))))")
add_rule("rule_hub", "supply_chain", "x1(?(?(?(x2))))", "x1(?(#c(?(x2))))")
add_rule("rule_non_top", "supply_chain", "x(?)", "x(?(?))")
add_rule("rule_folded", "key_step_3d_51", "x1(x2(x3), x4(x5))", "x1(x2(#c, x4, x5))")
add_rule("rule_middle_hub", "embedding_neighbors", "x1(?(x2))", "x1(#c(x2))")
add_rule("rule_hidden_branch", "purchase_tree", "x1(?(?), x2)", "x1(x2(#c))")
add_rule("rule_target", "site_graph", "x1(x2(?))", "x1(x2(#c))")

for _g in GRAPHS:
    add(f"rule_sparsity_{_g}", lambda s, d, g=_g: conf(sparsity_confidence(graph(g, s, d))), with_edges(_g, "SELECT CAST(sum(c) AS BIGINT) AS freq, CAST(sum(c * c) AS BIGINT) AS lhs_freq, round(CAST(sum(c) AS DOUBLE) / sum(c * c), 6) AS conf FROM (SELECT count(*) AS c FROM edge GROUP BY src) q"))
    add(f"rule_edge_share_{_g}", lambda s, d, g=_g: conf(edge_share(graph(g, s, d))), with_edges(_g, "SELECT dst AS pin1, count(*) AS freq, (SELECT count(*) FROM edge) AS lhs_freq, round(count(*) / CAST((SELECT count(*) FROM edge) AS DOUBLE), 6) AS conf FROM edge GROUP BY dst"))
add("rule_node_share", lambda s, d: conf(node_share(graph("page_links", s, d))), with_edges("page_links", "SELECT dst AS pin1, count(*) AS freq, (SELECT count(DISTINCT src) FROM edge) AS lhs_freq, round(count(*) / CAST((SELECT count(DISTINCT src) FROM edge) AS DOUBLE), 6) AS conf FROM edge GROUP BY dst"))
add("rule_extension", lambda s, d: conf(extension_share(graph("site_graph", s, d))), with_edges("site_graph", "SELECT count(*) FILTER (dst IN (SELECT src FROM edge)) AS freq, count(*) AS lhs_freq, round(count(*) FILTER (dst IN (SELECT src FROM edge)) / CAST(count(*) AS DOUBLE), 6) AS conf FROM edge"))


def add_pinned_rule(name: str, g: str, lhs: str, rhs: str, fold: tuple[int, ...], minsup: int, minconf: str, strategy: str = "fold") -> None:
    """A rule whose lhs has pins: one join of two support tables."""
    left, right = pure(parse_pattern(lhs).pattern), parse_pattern(rhs).pattern
    k = len(right.pins)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        data = kept(g, spark, sf_dir)
        table = support_table(data, right, minsup=minsup, strategy=strategy)
        own = support_table(data, left.body, minsup=minsup)
        lhs_rows = own.select(*[F.col(n(i)).alias(n(fold[i])) for i in left.body.pins], F.col("freq").alias("lhs_freq"))
        both = table.join(lhs_rows, [n(fold[i]) for i in left.body.pins])
        num, _, den = minconf.partition("/")
        both = both.filter(F.col("freq") * int(den) >= F.col("lhs_freq") * int(num))
        return conf(both.select(*[F.col(n(i)).alias(f"pin{j}") for j, i in enumerate(right.pins, 1)], "freq", "lhs_freq"))

    num, _, den = minconf.partition("/")
    on = " AND ".join(f"l.pin{j} = r.pin{right.pins.index(fold[i]) + 1}" for j, i in enumerate(left.body.pins, 1))
    pins = ", ".join(f"r.pin{j}" for j in range(1, k + 1))
    sql = f"SELECT {pins}, r.freq, l.freq AS lhs_freq, round(CAST(r.freq AS DOUBLE) / l.freq, 6) AS conf FROM ({to_sql(right, minsup=minsup)}) r JOIN ({to_sql(left.body)}) l ON {on} WHERE r.freq * {den} >= {num} * l.freq"
    add(name, run, with_edges(g, sql))


add_pinned_rule("rule_pair", "embedding_neighbors", "x1(x2(#a))", "x1(x2(#a, #b))", (0, 1, 2), 20, "1/2")
add_pinned_rule("rule_pair_star", "supplier_part", "x1(#a)", "x1(#a, #b)", (0, 1), 18, "3/5", "blocks")
add_pinned_rule("rule_pair_citations", "customer_part", "x1(#a)", "x1(#a, #b)", (0, 1), 5, "1/5", "blocks")

RULE_LHS = TreeQuery((0, 2), parse_pattern("x(#a, z)").pattern)
RULE_FOLDS = rules.folds_into(RULE_LHS, [p for t in shapes(3) for p in all_marks(t, "full")])


def rules_all_fork(spark: SparkSession, sf_dir: str, graph_name: str = "key_step_3d_22", minsup: int = 10) -> DataFrame:
    g = kept(graph_name, spark, sf_dir)
    found = rules.mine_rules(mine(g, minsup, 3).tables, RULE_LHS, "0.3", g)
    fold = F.concat_ws(",", F.col("fold").cast("array<string>"))
    return conf(found.select(F.col("rhs_key"), fold.alias("fold"), F.col("lhs_pins")[0].alias("lhs_pin1"), *[F.get("rhs_pins", F.lit(k)).alias(f"pin{k + 1}") for k in range(3)], "freq", "lhs_freq"))


def rule_counts(spark: SparkSession, sf_dir: str, graph_name: str = "key_step_3d_22", minsup: int = 10) -> DataFrame:
    """Rules of the fork at two confidences, counted by instances and by queries on the right side."""
    g = kept(graph_name, spark, sf_dir)
    tables = mine(g, minsup, 3).tables
    return reduce(DataFrame.unionByName, [rules.count_rules(rules.mine_rules(tables, RULE_LHS, c, g)).select(F.lit(c).alias("minconf"), "instances", "rhs_queries") for c in ("0.2", "0.5")])


add("rule_counts", rule_counts, with_edges("key_step_3d_22", " UNION ALL ".join(f"SELECT '{c}' AS minconf, count(*) AS instances, count(DISTINCT rhs_key || '/' || fold) AS rhs_queries FROM ({rules_sql(RULE_LHS, RULE_FOLDS, 10, int(c[2:]), 10, 3)}) r{c[2:]}" for c in ("0.2", "0.5"))))


def rules_live_fork(spark: SparkSession, sf_dir: str, graph_name: str = "key_step_3d_22", minsup: int = 10) -> DataFrame:
    """The same rules, each tree's as soon as the tree is mined."""
    found = rules.mine_rules_live(kept(graph_name, spark, sf_dir), RULE_LHS, minsup, "0.3", 3)
    fold = F.concat_ws(",", F.col("fold").cast("array<string>"))
    return conf(found.select(F.col("rhs_key"), fold.alias("fold"), F.col("lhs_pins")[0].alias("lhs_pin1"), *[F.get("rhs_pins", F.lit(k)).alias(f"pin{k + 1}") for k in range(3)], "freq", "lhs_freq"))


add("rules_live_fork", rules_live_fork, with_edges("key_step_3d_22", rules_sql(RULE_LHS, RULE_FOLDS, 10, 3, 10, 3)))


def mine_resume(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A search with a catalog, ended inside the trees of three nodes and taken up again."""
    from .storage import shared_folder

    g = kept("page_links", spark, sf_dir)
    catalog = Catalog(spark, f"{shared_folder(spark)}/catalog-{uuid.uuid4().hex}")
    mine(g, 5, budget=Budget(max_nodes=3, max_patterns=300), catalog=catalog)
    return padded(mine(g, 5, 3, catalog=catalog).tables.support, 3, "pattern_key")


add("mine_resume", mine_resume, with_edges("page_links", tall_sql([p for t in shapes(3) for p in all_marks(t, "full")], 5, 3)))

add("rules_all_fork", rules_all_fork, with_edges("key_step_3d_22", rules_sql(RULE_LHS, RULE_FOLDS, 10, 3, 10, 3)))


def _store(spark: SparkSession, sf_dir: str, graph_name: str = "key_step_3d_22", minsup: int = 10) -> Tables:
    return mine(kept(graph_name, spark, sf_dir), minsup, 3, strategy="cube").tables


_ALL3 = tall_sql([p for t in shapes(3) for p in all_marks(t, "full")], 10, 3)
_TALL3 = f"tall AS MATERIALIZED (SELECT *, concat_ws(',', pin1, pin2, pin3) AS pins, CAST(length(regexp_replace(pattern_key, '[^dep]', '', 'g')) AS INTEGER) AS n_nodes FROM ({_ALL3}) a)"


def _tall(body: str) -> str:
    return f"WITH edge AS MATERIALIZED ({edge_sql('key_step_3d_22')}), {_TALL3} {body}"


add(
    "browse_instances", lambda s, d: browse.instances(_store(s, d), "x(#a, z)").select(F.col("a").alias("pin1"), "freq"),
    with_edges("key_step_3d_22", to_sql(parse_pattern("x(#a, z)").pattern, minsup=10)),
)
add("browse_suggest", lambda s, d: browse.suggest(_store(s, d), 5), _tall("SELECT n_nodes, pattern_key, pins, freq, place FROM (SELECT *, CAST(row_number() OVER (PARTITION BY n_nodes ORDER BY freq DESC, pattern_key, pins) AS INTEGER) AS place FROM tall) q WHERE place <= 5"))
add("browse_hot_constants", lambda s, d: browse.hot_constants(_store(s, d), 10), _tall("SELECT constant, count(DISTINCT pattern_key) AS patterns, count(*) AS instances FROM (SELECT pattern_key, pin1 AS constant FROM tall UNION ALL SELECT pattern_key, pin2 FROM tall UNION ALL SELECT pattern_key, pin3 FROM tall) q WHERE constant IS NOT NULL GROUP BY constant ORDER BY patterns DESC, instances DESC, constant LIMIT 10"))


def db_diff(spark: SparkSession, sf_dir: str, graph_name: str = "key_step_3d_22", minsup: int = 10, higher: int = 25) -> DataFrame:
    """What a higher support threshold leaves out of a database at a lower one."""
    a = _store(spark, sf_dir, graph_name, minsup).support
    b = mine(kept(graph_name, spark, sf_dir), higher, 3, strategy="cube").tables.support
    return diff(a, b).select("pattern_key", F.concat_ws(",", "pins").alias("pins"), "freq_a", "freq_b")


add("db_diff", db_diff, _tall("SELECT pattern_key, pins, freq AS freq_a, CAST(NULL AS BIGINT) AS freq_b FROM tall WHERE freq < 25"))


# The searches above that run on a part of the step graph, on whole graphs.  SQL only where it is no brute force over all marks of a shape.
WHOLE, WHOLE_MINSUP = "page_links", 25
for _name, _size, _how in (
    ("mine_v1_size3", 3, {"dedup": "none", "order": "double"}), ("mine_v2_size4", 4, {"min_height": 2}), ("mine_cube_size4", 4, {"strategy": "cube"}),
    ("mine_no_copies_size3", 3, {"dedup": "canonical"}), ("mine_no_redundancy_size3", 3, {"dedup": "redundancy"}), ("mine_expand_size3", 3, {"strategy": "expand"}),
):
    # Page links alone have no paths of two edges.
    add(f"{_name}_whole", _mined("site_graph" if "min_height" in _how else WHOLE, WHOLE_MINSUP, _size, **_how)[0])
for _k, _text in enumerate(("x(#a, z)", "#r(#a, z)", "?(#a, #b)"), 1):
    add(f"cand_join_level{_k}_whole", _candidates(_text, WHOLE_MINSUP, WHOLE)[0])
add("rule_counts_whole", lambda s, d: rule_counts(s, d, WHOLE, WHOLE_MINSUP))
add("rules_live_fork_whole", lambda s, d: rules_live_fork(s, d, WHOLE, WHOLE_MINSUP))
add("rules_all_fork_whole", lambda s, d: rules_all_fork(s, d, WHOLE, WHOLE_MINSUP))
add(
    "browse_instances_whole", lambda s, d: browse.instances(_store(s, d, WHOLE, WHOLE_MINSUP), "x(#a, z)").select(F.col("a").alias("pin1"), "freq"),
    with_edges(WHOLE, to_sql(parse_pattern("x(#a, z)").pattern, minsup=WHOLE_MINSUP)),
)
add("browse_suggest_whole", lambda s, d: browse.suggest(_store(s, d, WHOLE, WHOLE_MINSUP), 5))
add("browse_hot_constants_whole", lambda s, d: browse.hot_constants(_store(s, d, WHOLE, WHOLE_MINSUP), 10))
add("db_diff_whole", lambda s, d: db_diff(s, d, WHOLE, WHOLE_MINSUP, 2 * WHOLE_MINSUP))
add("match_fork_whole", *_matchings("key_step_30d", "x(y, z)"))
add("match_path_whole", *_matchings("key_step_30d", "x(y(z))"))
add(
    "match_hub_whole", lambda s, d: answer_set(graph("key_step_30d", s, d), (0, 2, 0), parse_pattern("#a(?(x))").pattern),
    with_edges("key_step_30d", "SELECT DISTINCT e1.src AS h1, e2.dst AS h2, e1.src AS h3 FROM edge e1 JOIN edge e2 ON e2.src = e1.dst"),
)
add("rule_folded_whole", lambda s, d: conf(rules.ratio(graph("key_step_30d", s, d), parse_pattern("x1(x2(x3), x4(x5))").pattern, parse_pattern("x1(x2(#c, x4, x5))").pattern, {})))


def labels_as_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .graph import with_node_labels
    from .sources.datagraphs import named, table

    links = table(spark, sf_dir, "documents").select(F.col("source").alias("src"), named("d:", "doc_id").alias("dst"))
    labels = table(spark, sf_dir, "documents").select(named("d:", "doc_id").alias("id"), F.col("lang").alias("label"))
    p = parse_pattern("#s(x(#l))").pattern
    return numbered(support_table(with_node_labels(load(links), labels), p), p)


add("labels_as_nodes", labels_as_nodes, "SELECT source AS pin1, 'label:' || lang AS pin2, count(DISTINCT doc_id) AS freq FROM documents GROUP BY source, lang")


def edge_labels_reified(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .graph import reify_edge_labels
    from .sources.datagraphs import keyed_events, named

    e = keyed_events(spark, sf_dir).select(named("u:", "user_id").alias("src"), named("k:", "k").alias("dst"), F.col("event_type").alias("label"), named("e:", "event_id").alias("edge_id"))
    named_p = parse_pattern("#u(x(?k, #t))").pattern
    g = reify_edge_labels(e)
    rows = numbered(support_table(g, named_p), named_p)
    return rows.filter(F.col("pin1").startswith("u:") & F.col("pin2").startswith("label:"))


add("edge_labels_reified", edge_labels_reified, "SELECT 'u:' || user_id AS pin1, 'label:' || event_type AS pin2, count(DISTINCT event_id) AS freq FROM events GROUP BY user_id, event_type")


def fold_maps_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fold maps of the fork into every pattern that the page links hold often: made and with a legal head, on executors."""
    from .functions.udfs import register

    register(spark)
    _store(spark, sf_dir, WHOLE, WHOLE_MINSUP).support.select(F.col("pattern_key").alias("rhs_key")).distinct().createOrReplaceTempView("stored_patterns")
    return spark.sql(f"SELECT rhs_key, count(*) AS made, count_if(legal) AS legal FROM stored_patterns, LATERAL fold_maps('{RULE_LHS.body.refined()}', rhs_key) GROUP BY rhs_key")


add("fold_maps_count", fold_maps_count)


def rule_dedup_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Folds of a three-leaved fork into the patterns that the page links hold often: made, legal, and kept by each way of removing repeats."""
    lhs = TreeQuery((0, 2, 3), parse_pattern("x1(#a, x3, x4)").pattern)
    keys = _store(spark, sf_dir, WHOLE, WHOLE_MINSUP).support.select("pattern_key").distinct()
    patterns = [pattern_of_key(r[0]) for r in keys.orderBy("pattern_key").collect()]
    rows = []
    for how in ("none", "linear", "complete"):
        c = rules.FoldCounts()
        rules.folds_into(lhs, patterns, how, c)
        rows.append((how, c.made, c.legal, c.kept))
    return spark.createDataFrame(rows, "dedup string, made int, legal int, kept int")


add("rule_dedup_counts", rule_dedup_counts)


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return padded(mine(kept("page_links", spark, sf_dir), 3, 3).tables.support, 3, "pattern_key")


for _module in (relops, stream_queries):
    QUERIES |= _module.QUERIES
    ORACLES |= _module.ORACLES

__all__ = ["ORACLES", "QUERIES", "entry", "fold_maps"]
