"""Support tables, searches and rules on small graphs with known answers."""

import re
from fractions import Fraction

import pytest
from pyspark.sql import functions as F

from twigmine.graph import decode, edge_share, encode, extension_share, load, reify_edge_labels, sparsity_confidence, stats, symmetric, with_node_labels
from twigmine.model.pattern import Pattern, all_marks, pattern_key
from twigmine.model.query import TreeQuery, parse_pattern, pure
from twigmine.model.shape import shapes
from twigmine.operators import browse, rules
from twigmine.operators.catalog import Catalog, diff
from twigmine.operators.miner import Budget, Metrics, brute_force, candidates, flock, mine, mine_tree, mine_tree_cube, per_instance, reduced_rows
from twigmine.plans.twig import answers, cube_tables, is_frequent, matchings, support, support_table

RUN = [(0, 1), (0, 2), (0, 3), (1, 4), (2, 4), (2, 5), (3, 6)]
HOM = [(0, 1), (0, 2), (1, 4), (2, 4), (2, 5), (4, 8), (4, 6), (5, 8), (5, 6), (1, 8), (2, 6), (2, 8), (6, 7), (6, 8), (7, 2), (7, 8)]
SPARSE = [(0, 1), (0, 2), (1, 3), (1, 4), (2, 5), (3, 6)]


def graph(spark, edges):
    return load(spark.createDataFrame(edges, "src bigint, dst bigint"))


@pytest.fixture(scope="module")
def run(spark):
    return graph(spark, RUN).persisted()


@pytest.fixture(scope="module")
def hom(spark):
    return graph(spark, HOM).persisted()


def table(g, text, minsup=1, strategy="fold"):
    p = parse_pattern(text).literal() if "=" in text else parse_pattern(text)
    return {tuple(r[:-1]): r[-1] for r in support_table(g, p.pattern, None, minsup, strategy).collect()}


def rows(df):
    return sorted((r.pattern_key, tuple(r.pins), r.freq) for r in df.collect())


WORKED = [
    ("x(y,z)", {(): 15}), ("#r(y,z)", {(0,): 9, (2,): 4}), ("x(#c,z)", {(i,): 3 for i in (1, 2, 3, 4)}), ("#r(#c,z)", {(0, 1): 3, (0, 2): 3, (0, 3): 3}), ("x(#b,#c)", {}),
    ("?(y,z)", {(): 14}), ("?(#c,z)", {(i,): 3 for i in (1, 2, 3)}), ("?(#b,#c)", {}), ("x(?,z)", {(): 7}), ("#r(?,z)", {(0,): 3}), ("x(?,#c)", {}), ("?(?,z)", {(): 6}), ("x(?,?)", {(): 4}),
]


@pytest.mark.parametrize(("text", "expected"), WORKED)
def test_worked_run(run, text, expected):
    for strategy in ("fold", "expand"):
        assert table(run, text, 3, strategy) == expected


def test_homomorphism_examples(hom):
    bound = lambda text: parse_pattern(text).literal()
    named = bound("#0(x(?y(#8,#6)))")
    constants = {i: int(v) for i, v in named.constants.items()}
    found = matchings(hom, named.pattern, constants)
    assert sorted((r.n1, r.n2) for r in found.collect()) == [(1, 4), (2, 4), (2, 5)]
    assert support(hom, named.pattern, constants) == 2
    for text, freq in (("#0(x1(?(#8)), x2(?(x3)))", 10), ("#0(x2(#8, x4))", 6), ("#0(x2(#8, #4))", 2)):
        q = bound(text)
        assert support(hom, q.pattern, {i: int(v) for i, v in q.constants.items()}) == freq
    assert tuple(sparsity_confidence(hom).first()) == (16, 40)
    assert is_frequent(hom, named.pattern, constants, 2) and not is_frequent(hom, named.pattern, constants, 3)


def test_sparse(spark):
    assert tuple(sparsity_confidence(graph(spark, SPARSE)).first()) == (6, 10)


@pytest.mark.parametrize("n", [4, 10])
def test_friends(spark, n):
    pairs = [e for i in range(n) for e in ((2 * i, 2 * i + 1), (2 * i + 1, 2 * i), (2 * i, 99), (2 * i + 1, 99))]
    g = graph(spark, pairs)
    lhs, rhs = parse_pattern("?(x1,x2)").pattern, parse_pattern("?(x1,#h)").pattern
    assert (support(g, rhs, {2: 99}), support(g, lhs)) == (2 * n + 1, 6 * n + 1)
    clique = [(1000 + a, 1000 + b) for a in range(n) for b in range(n) if a != b]
    g2 = graph(spark, pairs + clique)
    assert (support(g2, rhs, {2: 99}), support(g2, lhs)) == (2 * n + 1, n * n + 6 * n + 1)


def test_strategies_agree(spark, hom):
    import random

    r = random.Random(3)
    g2 = graph(spark, [(r.randrange(9), r.randrange(9)) for _ in range(30)])
    patterns = [p for t in shapes(5) for p in all_marks(t, "canonical")]
    for g in (hom, g2):
        for p in r.sample(patterns, 12):
            a, b = (sorted(map(tuple, support_table(g, p, strategy=s).collect())) for s in ("fold", "expand"))
            assert a == b, p
            if p.pins:
                some = support_table(g, p).orderBy("freq", *[f"n{i}" for i in p.pins]).limit(3).drop("freq")
                probe = sorted(map(tuple, support_table(g, p, strategy="probe", candidates=some).collect()))
                assert probe == [x for x in a if x[:-1] in {tuple(c) for c in some.collect()}]


def test_cube_holds_every_table(hom):
    p = parse_pattern("x(y,?(z))").pattern
    found = {}
    for r in cube_tables(hom, p, 2).collect():
        found.setdefault(r.marks, {})[tuple(r.pins)] = r.freq
    for marks in found:
        q = Pattern(p.levels, marks)
        assert found[marks] == {tuple(r[:-1]): r[-1] for r in support_table(hom, q, minsup=2, strategy="expand").collect()}


def test_searches_give_one_answer(run):
    want = rows(brute_force(run, 3, 3))
    found = mine(run, 3, 3)
    assert rows(found.tables.support) == want
    assert [sum(1 for k, *_ in {(k,) for k, *_ in want} if len(k) == 2 * n) for n in (1, 2, 3)] == [1, 4, 15]
    plain = mine(run, 3, 3, dedup="none", order="double")
    assert rows(reduced_rows(plain.tables.support)) == want
    assert plain.metrics.support_queries > found.metrics.support_queries
    assert rows(mine(run, 3, 3, strategy="cube").tables.support) == want
    assert rows(mine(run, 3, 3, strategy="auto").tables.support) == want
    assert found.metrics.patterns == len(want) == 28
    assert found.metrics.pruned["redundant"] > 0 and found.metrics.pruned["copy"] > 0


def test_searches_on_random_graphs(spark):
    """All parents' tables met where their pins come together."""
    import random

    r = random.Random(4)
    g = graph(spark, sorted({(r.randrange(7), r.randrange(7)) for _ in range(16)}))
    for levels in ((0, 1, 1), (0, 1, 2)):
        want = {}
        for p in all_marks(levels, "full"):
            for x in support_table(g, p, minsup=4, strategy="expand").collect():
                want[p.refined(), tuple(x[:-1])] = x[-1]
        for found in (mine_tree(g, levels, 4), mine_tree_cube(g, levels, 4, Metrics())):
            assert {(x.pattern_key, tuple(x.pins)): x.freq for x in found.collect()} == want


def test_candidates_are_what_all_generalisations_allow(run):
    found = mine_tree(run, (0, 1, 1), 3)
    from twigmine.operators.catalog import Tables

    store = Tables(found)
    p = parse_pattern("#r(#c,z)").pattern
    got = {tuple(r) for r in candidates(p, store, run).collect()}
    roots, kids = {0, 2}, {1, 2, 3, 4}
    assert got == {(a, b) for a in roots for b in kids}
    assert candidates(parse_pattern("x(#c,z)").pattern, store, run).count() == 7


def test_flock_and_single_counts(run):
    p = parse_pattern("#r(#c,z)").pattern
    found = {r.pattern_key: 0 for r in flock(run, p, 3).tables.support.collect()}
    assert set(found) == {pattern_key(parse_pattern(t).pattern) for t in ("x(y,z)", "#r(y,z)", "x(#c,z)", "#r(#c,z)")}
    deep = {(r.pattern_key, tuple(r.pins)): r.freq for r in flock(run, parse_pattern("#r(?(#c),z)").pattern, 2).tables.support.collect()}
    for t in ("x(?(y),z)", "#r(?(y),z)", "x(?(#c),z)", "#r(?(#c),z)"):
        q = parse_pattern(t).pattern
        assert {k: v for (name, k), v in deep.items() if name == pattern_key(q)} == {tuple(r[:-1]): r[-1] for r in support_table(run, q, minsup=2, strategy="expand").collect()}
    one = dict(per_instance(run, parse_pattern("#r(#c,z)").pattern, 3))
    assert one == table(run, "#r(#c,z)", 3)
    with pytest.raises(ValueError):
        per_instance(run, parse_pattern("#r(#c,#d)").pattern, 3)


def test_budget_and_restart(run, spark, tmp_path):
    catalog = Catalog(spark, str(tmp_path / "db"), "bigint")
    assert catalog.finished() == set() and catalog.support.count() == 0
    mine(run, 3, budget=Budget(max_nodes=2), catalog=catalog)
    assert catalog.finished() == {"0", "0-1"}
    second = mine(run, 3, 3, catalog=catalog)
    assert second.metrics.trees == 2 and rows(catalog.support) == rows(brute_force(run, 3, 3))
    p = parse_pattern("x(z, #c)").pattern
    assert {tuple(r.pins): r.freq for r in catalog.table(p).collect()} == {(i,): 3 for i in (1, 2, 3, 4)}
    assert catalog.pinless().count() == len([k for k in catalog.keys() if "p" not in k])
    catalog.export(str(tmp_path / "out"), p)
    assert spark.read.option("header", "true").csv(str(tmp_path / "out")).count() == 4
    assert diff(catalog.support, catalog.support).count() == 0
    # Another threshold, dedup or graph is refused: its tables would be mixed with these.
    for other in (lambda: mine(run, 1, 2, catalog=catalog), lambda: mine(run, 3, 2, "none", catalog=catalog), lambda: mine(graph(spark, [(0, 1)]), 3, 2, catalog=catalog)):
        with pytest.raises(ValueError):
            other()
    # A tree that was cut short is taken up again.
    third = Catalog(spark, str(tmp_path / "short"), "bigint")
    first = mine(run, 3, budget=Budget(max_nodes=3, max_patterns=8), catalog=third)
    assert first.metrics.cut_short and 0 < third.support.count() < 28 and len(third.finished()) < 4
    mine(run, 3, 3, catalog=third)
    assert rows(third.support) == rows(brute_force(run, 3, 3))
    with pytest.raises(ValueError):
        mine(run, 3)
    with pytest.raises(ValueError):
        mine(run, 0, 2)
    assert mine(run, 3, budget=Budget(max_patterns=1, max_nodes=5)).metrics.trees == 1


@pytest.fixture(scope="module")
def store(run):
    return mine(run, 3, 3, strategy="cube").tables


LHS = TreeQuery((0, 2, 3), parse_pattern("x1(#a, x3, x4)").pattern)


def test_worked_rules(run, store):
    lhs = rules.lhs_table(LHS, store, run, 3)
    assert {tuple(r.lhs_pins): r.lhs_freq for r in lhs.collect()} == {(1,): 9, (2,): 9, (3,): 9, (4,): 5, (5,): 4}
    found = rules.mine_rules(store, LHS, Fraction(3, 10), run)
    on_free = [(tuple(r.lhs_pins), tuple(r.rhs_pins), r.freq, r.lhs_freq) for r in found.filter(F.col("rhs_key") == "0d1p1d").collect()]
    assert sorted(set(on_free)) == [((1,), (1,), 3, 9), ((2,), (2,), 3, 9), ((3,), (3,), 3, 9), ((4,), (4,), 3, 5)] and len(on_free) == 12
    pinned = [(tuple(r.lhs_pins), tuple(r.rhs_pins)) for r in found.filter(F.col("rhs_key") == "0p1p1d").collect()]
    assert sorted(set(pinned)) == [((1,), (0, 1)), ((2,), (0, 2)), ((3,), (0, 3))] and len(pinned) == 9
    full = rules.mine_rules(store, LHS, "0.3", run, "complete").filter(F.col("rhs_key") == "0d1p1d")
    assert full.count() == 8


def test_rules_are_those_of_brute_force(run, store):
    for lhs in (LHS, TreeQuery((0, 2), parse_pattern("x(#a,z)").pattern), pure(parse_pattern("x(y)").pattern), TreeQuery((0, 1, 0), parse_pattern("#r(x)").pattern)):
        patterns = store.patterns()
        want = sorted(rules.brute_rules(run, lhs, [p for p in patterns if p.height >= lhs.body.height], 3, "0.3"))
        got = sorted((r.rhs_key, tuple(r.fold), tuple(r.lhs_pins), tuple(r.rhs_pins), r.freq, r.lhs_freq) for r in rules.mine_rules(store, lhs, "0.3", run, "none").collect())
        assert got == want
        for r in got:
            assert 0 < r[4] <= r[5]


def test_live_rules_and_one_fold(run, store):
    lhs = TreeQuery((0, 2), parse_pattern("x(#a,z)").pattern)
    live = rules.mine_rules_live(run, lhs, 3, "0.3", 3)
    assert live.exceptAll(rules.mine_rules(store, lhs, "0.3", run)).count() == 0
    trees = dict(rules.rules_by_tree(run, lhs, 3, "0.3", 3))
    assert list(trees) == [(0, 1), (0, 1, 2), (0, 1, 1)] and sum(t.count() for t in trees.values()) == live.count() > 0
    counted = rules.count_rules(live).first()
    assert counted.instances == live.count() and counted.rhs_queries == len({(r.rhs_key, tuple(r.fold)) for r in live.collect()})
    one = rules.rule_table(store, lhs, parse_pattern("#r(#a,z)").pattern, (0, 1, 2), "0.1", run)
    assert {(tuple(r.rhs_pins), r.freq, r.lhs_freq) for r in one.collect()} == {((0, i), 3, 3) for i in (1, 2, 3)}


def test_purified_rules_keep_their_confidence(hom):
    lhs = TreeQuery((0, 1, 1, 2), parse_pattern("#r(x(y))").pattern)
    rhs = parse_pattern("#r(x(#c))").pattern
    rule = rules.rule_of_fold(lhs, rhs, (0, 1, 2))
    clean = rules.purify_rule(rule)
    assert clean.lhs.is_pure() and rule.is_legal() and clean.is_legal()
    alpha = {0: 0, 2: 8}
    assert rules.confidence(hom, rule, alpha) == rules.confidence(hom, clean, alpha)
    assert rules.passes(2, 6, 2, "1/3") and not rules.passes(2, 6, 2, "0.34")


def test_browsing(run, store):
    assert {(r.r, r.freq) for r in browse.instances(store, "#r(y,z)").collect()} == {(0, 9), (2, 4)}
    assert [r.freq for r in browse.instances(store, "#r(#c,z)", c=2).collect()] == [3]
    assert browse.suggest(store, 1, per_size=False).first().freq == 15
    assert browse.hot_constants(store, 1).first().constant in (0, 1, 2, 3)
    found = browse.rules(store, LHS, [4], "0.3", run)
    assert {tuple(r.lhs_pins) for r in found.collect()} == {(4,)}
    assert browse.rule_instances(found, "0d1p1d", (0, 1, 1, 2)).count() == 1
    assert browse.compare(store, store).count() == 0


def test_shares(run):
    assert {(r.pin1, r.freq) for r in edge_share(run).collect()} == {(1, 1), (2, 1), (3, 1), (4, 2), (5, 1), (6, 1)}
    assert tuple(extension_share(run).first()) == (3, 7)


def test_edge_cases(spark):
    none = graph(spark, [])
    assert support(none, parse_pattern("x(y)").pattern) == 0 and mine(none, 1, 2).tables.support.count() == 0
    loop = graph(spark, [(1, 1), (1, 1)])
    assert support(loop, parse_pattern("x(y(z))").pattern) == 1 and stats(loop).first().n_edges == 1
    star = graph(spark, [(0, i) for i in range(1, 30)])
    assert support(star, parse_pattern("x(y,z)").pattern) == 29 * 29
    g = load(spark.createDataFrame([("a,b", "c"), ("a,b", None), (None, "c")], "src string, dst string"), count_dropped=True)
    assert g.dropped == 2 and support(g, parse_pattern("x").pattern) == 2
    assert support(loop, parse_pattern("?(?)").pattern) == 1 and support(loop, parse_pattern("#a(#b)").pattern, {0: 1, 1: 1}) == 1
    assert answers(loop, parse_pattern("x(#a)").pattern, {1: 1}).count() == 1


def test_encoding(spark):
    g = load(spark.createDataFrame([("b", "a"), ("c", "b"), ("a", "c")], "src string, dst string"))
    coded, names = encode(g)
    assert sorted(tuple(r) for r in names.collect()) == [(0, "a"), (1, "b"), (2, "c")]
    assert sorted(map(tuple, decode(coded.edges, names, ["src", "dst"]).select("src", "dst").collect())) == [("a", "c"), ("b", "a"), ("c", "b")]


def test_labels(spark, run):
    labels = spark.createDataFrame([(1, "red"), (2, "red")], "id bigint, label string")
    g = with_node_labels(run, labels)
    assert support(g, parse_pattern("x(#l)").pattern, {1: "label:red"}) == 2
    e = spark.createDataFrame([(1, 2, "likes", "e1"), (1, 3, "hates", "e2")], "src bigint, dst bigint, label string, edge_id string")
    assert reify_edge_labels(e).edges.count() == 6
    assert symmetric(run).edges.count() == 14


def test_blocks_count_pairs_of_children_in_their_tasks(spark, monkeypatch):
    """Same table as the join; children of one parent are never paired by Spark; rare children, hubs and blocks without a row."""
    import random

    from twigmine.plans import pairs
    from twigmine.queries import QUERIES

    r = random.Random(3)
    edges = {(a, b) for a in range(60) for b in range(40) if r.random() < 0.3} | {(7, b) for b in range(200)} | {(a, 1000 + a) for a in range(60)}
    g = load(spark.createDataFrame(sorted((f"s{a}", f"p{b}") for a, b in edges), "src string, dst string"))
    p = parse_pattern("x(#a,#b)").pattern
    monkeypatch.setattr(pairs, "AT_ONCE", 50)
    for minsup in (1, 9):
        want = sorted(map(tuple, support_table(g, p, minsup=minsup).collect()))
        assert want and sorted(map(tuple, support_table(g, p, minsup=minsup, strategy="blocks").collect())) == want
        assert sorted(map(tuple, pairs.common_parents(g, minsup, blocks=3).collect())) == want
    assert {tuple(x) for x in support_table(graph(spark, RUN), p, minsup=1, strategy="blocks").collect()} == {tuple(x) for x in support_table(graph(spark, RUN), p).collect()}
    with pytest.raises(ValueError):
        support_table(g, parse_pattern("x(#a,b)").pattern, strategy="blocks")
    for name in ("sup_pair_star", "rule_pair_star", "rule_pair_citations"):
        plan = QUERIES[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().optimizedPlan().toString()
        assert "FlatMapGroupsInArrow" in plan and "Join Inner, (src" not in plan


@pytest.mark.parametrize("text", ["x1(x2(#a, #b))", "x1(x2(#a))", "x1(x2(x3(#a, ?), y), z)", "x1(x2(#a(y), #b), z)", "x1(x2(?(#a, #b)), z)", "x1(#a(x2, #b))"])
def test_free_nodes_above_the_pins_are_counted_from_the_root(spark, hom, text):
    p = parse_pattern(text).pattern
    table = support_table(hom, p, minsup=2)
    assert sorted(map(tuple, table.collect())) == sorted(map(tuple, support_table(hom, p, minsup=2, strategy="expand").collect()))
    if text in ("x1(x2(#a, #b))", "x1(x2(#a))"):
        # No row for a pin and a free node above its parent.
        plan = table._jdf.queryExecution().optimizedPlan().toString()
        pins = {f"n{i}" for i in p.pins}
        keys = [set(re.findall(r"n\d+", k)) for k in re.findall(r"Aggregate \[([^\]]*)\]", plan)]
        assert keys and not [k for k in keys if "n0" in k and k & pins]


def test_wide_graphs_count_what_narrow_ones_do(spark, monkeypatch):
    from twigmine import graph as graphs

    # Hosts, pages of one host or of two, targets of many pages.
    edges = [(f"h{k % 3}", f"l{k}") for k in range(24)] + [("h1", "l0"), ("h2", "l0"), ("h2", "l1"), ("h0", "t0"), ("l3", "l5")]
    edges += [(f"l{k}", f"t{j}") for k in range(24) for j in range(6) if (k * 7 + j * j) % 4 < 2]
    g = load(spark.createDataFrame(edges, "src string, dst string")).persisted()
    assert not g.told_apart().wide  # few pairs: nothing changes
    monkeypatch.setattr(graphs, "MOST_PAIRS", 0)
    wide = g.told_apart()
    assert wide.wide and {r.dst for r in wide.edges.filter("lone").collect()} == {f"l{k}" for k in range(24)} - {"l0", "l1", "l5"}
    for text in (
        "?(x(y), z)", "?(x(?), z)", "?(x(#a), z)", "?(#a(x), z)", "?(x(y), #a)", "?(x(#a), #b)", "?(#a(x), #b)", "?(?(x), #a)", "?(?(#a), x)", "?(x, y, #a)", "?(#a, #b)",
        "x(y(#a), #b)", "x(#a(y), #b)", "x(?(#a), #b)", "#r(x(#a), #b)", "#r(?(x), #a)", "x(y(#a, #b))", "#r(x(#a, #b))", "x(?(y, z))", "x(?(y, #a))", "x(y, z(#a), #b)",
    ):
        p = parse_pattern(text).pattern
        assert sorted(map(tuple, support_table(wide, p, minsup=6).collect())) == sorted(map(tuple, support_table(g, p, minsup=6, strategy="expand").collect())), text
    monkeypatch.setattr("twigmine.operators.miner.MOST_ALLOWED", 5)
    rows = lambda x: sorted((r.pattern_key, tuple(r.pins), r.freq) for r in x.collect())
    found = rows(mine_tree(wide, (0, 1, 2, 1), 6))
    assert found and found == rows(mine_tree(g, (0, 1, 2, 1), 6))


def test_hidden_roots_of_many_children_pair_no_siblings(spark):
    # 400 million pairs of siblings under the first node.
    edges = [(0, k) for k in range(1, 20_001)] + [(k, -1 - k % 4) for k in range(1, 20_001)] + [(k, -5) for k in range(1, 1001)]
    g = graph(spark, edges).told_apart()
    assert g.wide
    assert support(g, parse_pattern("?(x(y), z)").pattern) == 21_000 * 20_000
    assert support_table(g, parse_pattern("x(#a(y), #b)").pattern, minsup=25).count() == 0
    assert sorted(map(tuple, support_table(g, parse_pattern("x(?(y, #a))").pattern, minsup=2).collect())) == [(-5, 5)] + [(-k, 2) for k in (4, 3, 2, 1)]
