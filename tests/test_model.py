"""Trees, patterns, folds and repeats, without Spark."""

from itertools import product

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from twigmine.model.contain import compose, contains, covers_free, equivalent, fold_maps, is_fold, match_matrix
from twigmine.model.pattern import HIDDEN, Pattern, all_marks, isomorphic, pattern_key, pattern_of_key, specializes
from twigmine.model.query import TreeQuery, freeze, parse_pattern, pure, purify, show, to_sql
from twigmine.model.ruledup import automorphisms, bipartite_to_folds, colored_isomorphic, digraph_to_bipartite, distinct_folds, equivalent_folds, fold_graph, fold_key_full, symmetry_count
from twigmine.model.shape import canonical_shape, parents_of, shapes


def pat(text):
    return parse_pattern(text).pattern


def small(n, dedup="full"):
    return [p for t in shapes(n) for p in all_marks(t, dedup)]


def test_shapes_by_size():
    assert [sum(1 for t in shapes(7) if len(t) == n) for n in range(1, 8)] == [1, 1, 2, 4, 9, 20, 48]
    assert all(canonical_shape(t) == t for t in shapes(7))
    assert all(max(t) >= 2 for t in shapes(5, min_height=2))
    assert canonical_shape((0, 1, 1, 2)) == (0, 1, 2, 1)
    assert parents_of((0, 1, 2, 1)) == (-1, 0, 1, 0)


@pytest.mark.parametrize(("dedup", "counts"), [("canonical", [3, 9, 45, 246, 1485]), ("full", [3, 9, 36, 174, 942])])
def test_pattern_counts(dedup, counts):
    assert [sum(1 for t in shapes(5) if len(t) == n for _ in all_marks(t, dedup)) for n in range(1, 6)] == counts


def test_with_a_free_node():
    assert [sum(1 for t in shapes(5) if len(t) == n for p in all_marks(t, "full") if p.free) for n in range(1, 6)] == [1, 5, 26, 144, 840]


def test_canonical_keys():
    a, b = pat("#1(?(#2,x1), x2(#3,x3))"), pat("#1(x2(x3,#3), ?(x1,#2))")
    assert pattern_key(a) == pattern_key(b) == "0p1e2p2d1d2p2d"
    assert a.refined() == "0p1e2p2d1d2p2d" and b.refined() == "0p1d2d2p1e2d2p"
    assert isomorphic(a, b) and pattern_of_key(pattern_key(a)) == a
    c, old = b.canonize()
    assert [b.marks[i] for i in old] == list(c.marks)


def test_redundancy_and_reduction():
    assert pat("x1(x2(x3),?(?))").has_redundancy() and pat("x1(x2(?,x3))").has_redundancy()
    assert not pat("x1(x2(x3))").has_redundancy() and not pat("x1(x2,?(x3))").has_redundancy()
    for t in ("x1(x2(x3),?(?))", "x1(x2(?,x3))", "x1(x2(x3),?(?,?))"):
        assert pat(t).normal()[0] == pat("x1(x2(x3))")
    for t in shapes(5):
        for p in all_marks(t, "redundancy"):
            for v in p.free:
                assert p.becomes_redundant(v) == p.marked(v, HIDDEN).has_redundancy()


def test_classes_are_the_keys_without_redundancy():
    for n, classes in ((3, 48),):
        reps = []
        for p in small(n, "none"):
            if not any(equivalent(p, q) for q in reps if len(q.free) == len(p.free) and len(q.pins) == len(p.pins)):
                reps.append(p)
        assert len(reps) == classes == len(small(n))


def test_same_size_without_redundancy_equivalent_means_isomorphic():
    ps = [p for p in small(4) if p.size == 4]
    for a, b in product(ps[:60], repeat=2):
        assert bool(equivalent(a, b)) == isomorphic(a, b)


def test_parents_and_specialisation():
    p = pat("#r(?(x), #b)")
    assert {q.marks for q in p.parents()} == {"dedp", "pddp", "pedd"} or len(p.parents()) == 3
    assert all(specializes(p, q) for q in p.parents())
    assert not specializes(p.parents()[0], p)
    assert specializes(p, p.parents()[0], {0: 1, 3: 2}, {}) and not specializes(p, p, {0: 1}, {0: 2})


def test_query_text():
    named = parse_pattern("#n(?(#p=p:8, x))")
    assert named.constants == {2: "p:8"} and named.names == ("n", "h1", "p", "x")
    assert named.bind(n="n:1").constants == {0: "n:1", 2: "p:8"}
    assert parse_pattern(show(named.pattern)).pattern == named.pattern
    for bad in ("x(", "x)y", "x y", "", "x=3", "#(y)"):
        with pytest.raises(ValueError):
            parse_pattern(bad)
    with pytest.raises(ValueError):
        named.bind(x="1")


def test_heads():
    p = pat("x(#a, ?(y))")
    q = TreeQuery((0, 1, 0, 3), p)
    assert not q.is_pure() and purify(q) == pure(p) and pure(p).is_pure() and pure(p).head == (0, 3)
    for head in ((0,), (0, 2, 3), (0, 3, 9)):
        with pytest.raises(ValueError):
            TreeQuery(head, p)


def test_fold_maps_are_all_the_maps():
    ps = small(3)
    for a, b in product(ps, ps):
        brute = {f for f in product(range(b.size), repeat=a.size) if is_fold(f, a, b)}
        assert set(fold_maps(a, b)) == brute
        assert (not brute) == (not any(match_matrix(a, b)[0]))


@settings(max_examples=60, deadline=None)
@given(st.sampled_from(small(3)), st.sampled_from(small(4)), st.sampled_from(small(4)))
def test_folds_compose(a, b, c):
    for f in list(fold_maps(a, b))[:4]:
        for g in list(fold_maps(b, c))[:4]:
            assert is_fold(compose(g, f), a, c)


def test_containment_is_what_frozen_bodies_say():
    """A query contains another just if it finds the frozen head in the frozen body."""
    ps = [p for p in small(3) if p.free]
    for a, b in product(ps, ps):
        qa, qb = pure(a), pure(b)
        if len(qa.head) != len(qb.head) or len(a.pins) != len(b.pins):
            continue
        edges, head, nodes = freeze(qb)
        after = {}
        for x, y in edges:
            after.setdefault(x, []).append(y)
        rho = dict(zip(a.pins, b.pins, strict=True))
        rows = [(x,) for x in nodes]
        for i in range(1, a.size):
            rows = [(*r, y) for r in rows for y in after.get(r[a.parent[i]], ())]
        found = any(tuple(r[h] for h in qa.head) == head and all(r[i] == nodes[j] for i, j in rho.items()) for r in rows)
        assert contains(qa, qb, rho) == found, (a, b)


def test_worked_folds_and_repeats():
    lhs, p = pat("x1(#a, x3, x4)"), pat("x1(#a, x3)")
    made = list(fold_maps(lhs, p))
    legal = [f for f in made if covers_free(f, p, lhs)]
    assert (len(made), len(legal)) == (4, 3)
    assert [len(distinct_folds(legal, lhs, p, d)) for d in ("none", "linear", "complete")] == [3, 3, 2]


def test_three_maps_are_one_class():
    lhs, p = pat("x1(x2, x3, x4)"), pat("u1(u2, u3)")
    maps = [(0, 1, 1, 2), (0, 1, 2, 1), (0, 2, 1, 1)]
    assert all(equivalent_folds(a, b, lhs, p) for a, b in product(maps, maps))
    assert len(distinct_folds(maps, lhs, p, "complete")) == 1


def test_keys_and_colored_graphs_agree():
    ps = small(3)
    for lhs in (pat("x(y,z)"), pat("x(y,z,?)"), pat("x(#a,#b,y)")):
        for p in ps:
            folds = list(fold_maps(lhs, p))[:6]
            for a, b in product(folds, folds):
                assert (fold_key_full(a, lhs, p) == fold_key_full(b, lhs, p)) == colored_isomorphic(fold_graph(a, lhs, p), fold_graph(b, lhs, p))


def test_symmetries():
    p = pat("x(y(a,b),z(c,d),w)")
    assert len(set(automorphisms(p))) == symmetry_count(p) == 8


def test_bipartite_graphs_as_folds():
    cycle6 = [(0, 0), (0, 1), (1, 1), (1, 2), (2, 2), (2, 0)]
    turned = [(2, 1), (2, 0), (0, 0), (0, 2), (1, 2), (1, 1)]
    other = [(0, 0), (0, 1), (1, 0), (1, 1), (2, 2), (2, 1)]
    lhs, rhs, f = bipartite_to_folds(3, 3, cycle6)
    lhs2, rhs2, g = bipartite_to_folds(3, 3, turned)
    lhs3, rhs3, h = bipartite_to_folds(3, 3, other)
    assert lhs == lhs2 == lhs3 and is_fold(f, lhs, rhs) and is_fold(h, lhs, rhs)
    assert equivalent_folds(f, g, lhs, rhs) and not equivalent_folds(f, h, lhs, rhs)
    assert len(digraph_to_bipartite([(0, 1), (1, 2)])) == 6


def test_sql_of_a_pattern():
    sql = to_sql(pat("#r(?(x))"), minsup=3)
    assert "DISTINCT" in sql and "HAVING count(*) >= 3" in sql and "e2.src = e1.dst" in sql


def test_bad_patterns():
    for levels, marks in (((0, 2), "dd"), ((0, 1), "d"), ((0, 0), "dd"), ((0,), "x"), ((), "")):
        with pytest.raises(ValueError):
            Pattern(levels, marks)
