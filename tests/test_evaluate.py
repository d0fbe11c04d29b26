from __future__ import annotations

import random

import pytest

from regpath.operators.reach import Evaluation
from regpath.operators.scratch import Scratch
from regpath.plans import evaluate as ev
from regpath.plans import structure as st
from regpath.plans import surface
from regpath.plans.query import CyclicQueryError, PathQuery, parse_query
from regpath.sources.graph import LabeledGraph
from tests.test_reach import got, graph, pairs


def brute(rows, q):
    """All maps of variables to vertices that satisfy every atom, atom by atom."""
    maps = [{}]
    for a in q.atoms:
        rel = pairs(rows, str(a.expr))
        maps = [{**m, a.x: x, a.y: y} for m in maps for x, y in rel if m.get(a.x, x) == x and m.get(a.y, y) == y]
    return {tuple(m[v] for v in q.head) for m in maps}


def rows_of(df, q):
    if not q.head:
        return {()} if df.first()["answer"] else set()
    assert df.columns == list(q.head)
    return got(df)


def test_random_queries(spark):
    rng = random.Random(11)
    exprs = ["a", "b", "a|b", "a*", "a/b", "^a", "c?", "(a|c)/^b", "b*/a"]
    for i in range(9):
        rows = sorted({(rng.randrange(5), rng.choice("abc"), rng.randrange(5)) for _ in range(rng.randint(3, 9))})
        g = graph(spark, rows)
        n = rng.randint(2, 6)
        edges = [(k, rng.randrange(k)) for k in range(1, n) if k == 1 or rng.random() < 0.9]
        atoms = [(rng.choice(exprs), *(f"v{x}" for x in (e if rng.random() < 0.5 else e[::-1]))) for e in edges]
        names = sorted({v for a in atoms for v in a[1:]})
        q = PathQuery.of([v for v in names if rng.random() < 0.5], atoms)
        want = brute(rows, q)
        order = rng.choice([None, "paths_first", rng.sample(names, len(names))])
        assert rows_of(ev.evaluate(q, g, order=order, skip_trivial_guards=rng.random() < 0.5), q) == want, (rows, str(q))
        if i % 3 == 0:
            assert rows_of(ev.evaluate(q, g, decomposition="single"), q) == want
            assert rows_of(ev.evaluate(q, g, contract_first=False), q) == want
            assert rows_of(ev.base_materialise(q, g), q) == want
            assert rows_of(ev.base_materialise(q, g, output_sensitive=True, limit=1), q) == want
            assert rows_of(ev.base_hypertree(q, g), q) == want
        if st.is_free_connex(q):
            kept = []
            assert rows_of(ev.eval_free_connex(q, g, keep=kept), q) == want
            for tree, m in kept:
                for a, df in m.relations.items():
                    if q.head and want and not isinstance(df, bool):
                        assert got(df) == {tuple(w[q.head.index(c)] for c in df.columns) for w in want}


FIXTURES = {
    "dangling": ([(1, "a", 2), (2, "b", 3), (2, "b", 4), (3, "c", 5)], "X, Y, U <- [a](X, Y), [b](Y, U), [c](U, W)", {(1, 2, 3)}),
    "vanish": ([(1, "a", 2)], "X <- [a](X, Y)", {(1,)}),
    "absent": ([(1, "a", 2)], " <- [zz](X, Y)", set()),
    "present": ([(1, "a", 2)], " <- [a](X, Y)", {()}),
    "composite": ([(1, "a", 2), (4, "a", 6), (2, "b", 3)], "X <- [a](X, Y), [b](Y, Z)", {(1,)}),
    "inverse": ([(1, "a", 3), (2, "b", 3)], "X, Z <- [a](X, Y), [b](Z, Y)", {(1, 2)}),
    "inverse_twice": ([(1, "a", 3), (2, "b", 3), (2, "c", 7)], "X, W <- [a](X, Y), [b](Z, Y), [c](Z, W)", {(1, 7)}),
    "star_split": ([(0, "a", 1), (5, "a", 6), (0, "b", 2), (5, "b", 2), (0, "c", 3), (5, "c", 8)], "A, C, E <- [a](O, A), [b](O, C), [c](O, E)", {(1, 2, 3), (6, 2, 8)}),
    "eps": ([(1, "a", 2)], "X, Y <- [a*](X, Y)", {(1, 1), (2, 2), (1, 2)}),
    "constant": ([(1, "a", 2), (3, "a", 4)], "Y <- [a](1, Y)", {(2,)}),
    "constant_middle": ([(1, "a", 2), (2, "b", 5), (3, "a", 4), (4, "b", 5)], "X, Y <- [a](X, 2), [b](2, Z), [b](Z2, Y)", {(1, 5)}),
}


@pytest.mark.parametrize("name", [n for n in FIXTURES if n != "constant_middle"])
def test_fixtures(spark, name):
    rows, text, want = FIXTURES[name]
    q, g = parse_query(text), graph(spark, rows)
    for order in (None, "paths_first"):
        assert rows_of(ev.evaluate(q, g, order=order), q) == want
    assert rows_of(ev.base_materialise(q, g), q) == want
    if not q.constants and len(q.atoms) < 3:
        assert rows_of(ev.base_bruteforce(q, g), q) == want


def test_dangling_rows_stay_without_child_filters(spark):
    rows, text, want = FIXTURES["dangling"]
    q, g, kept = parse_query(text), graph(spark, rows), []
    assert rows_of(ev.eval_free_connex(q, g, child_filters=False, keep=kept), q) == want
    assert got(kept[0][1].relations[q.atoms[1]]) == {(2, 3), (2, 4)}
    assert got(ev.calibrated(ev.evaluate(q, g), q.atoms[1])) == {(2, 3)}


def test_messages_of_the_four_atom_query(spark):
    q, kept = parse_query("X, Y, U <- [a](X, Y), [b](Y, Z), [c](Z, W), [d](X, U)"), []
    g = graph(spark, [(1, "a", 2), (2, "b", 3), (3, "c", 4), (1, "d", 5)])
    ev.eval_free_connex(q, g, keep=kept)
    tree, m = kept[0]
    n = {a: i + 1 for i, a in enumerate(q.atoms)}
    assert {(n[a], n[tree.parent[a]], tree.via[a]) for a in m.up} == {(3, 2, "Z"), (2, 1, "Y"), (4, 1, "X")}
    assert {(n[tree.parent[a]], n[a]) for a in m.down} == {(1, 2), (1, 4)}
    assert {n[a]: df.columns for a, df in m.relations.items()} == {1: ["X", "Y"], 2: ["Y"], 4: ["X", "U"]}


def test_own_decompositions(spark):
    rows, text, want = FIXTURES["star_split"]
    q, g = parse_query(text), graph(spark, rows)
    assert rows_of(ev.evaluate(q, g, decomposition=st.canonical_decomposition(q)), q) == want
    with pytest.raises(ValueError):
        ev.evaluate(q, g, decomposition=st.Decomposition((frozenset("AC"), frozenset("CE"), frozenset("OACE")), ((0, 2), (1, 2))))
    with pytest.raises(ValueError):
        ev.eval_free_connex(q, g)
    with pytest.raises(CyclicQueryError):
        ev.evaluate(parse_query("X <- [a](X, Y), [b](Y, X)"), g)


def test_string_vertices_and_reports(spark):
    g = LabeledGraph.from_edges(spark.createDataFrame([("a", "r", "b"), ("b", "s", "c")], "src string, label string, dst string"))
    how = Evaluation(Scratch(spark))
    assert got(surface.run(spark, "X, Z <- [r](X, Y), [s](Y, Z)", g, how)) == {("a", "c")}
    q = parse_query("X, Z <- [r](X, Y), [s](Y, Z)")
    assert "takes out ['Y']" in surface.explain_query(q, g)
    assert {r["stage"] for r in surface.explain_cost(q, g, how).collect()} >= {"bag", "result"}


def test_bounds_fall_with_width():
    q = parse_query("A, C, E <- [a](O, A), [b](O, C), [c](O, E)")
    b = ev.cost_bounds(q, 100, 1000, 25, 25)
    assert b["ctw"] == 1 and b["width_zero"] < b["driver"] == 1000 + 1000 * 5 * 10 + 25 * 100


def test_parts_agree_with_tables(spark):
    rng = random.Random(21)
    exprs = ["a", "b", "a|b", "a*", "a/b", "^a", "c?", "(a|c)/^b", "b*/a"]
    for i in range(12):
        rows, parted = [], []
        for part in range(3):
            own = sorted({(10 * part + rng.randrange(4), rng.choice("abc"), 10 * part + rng.randrange(4)) for _ in range(rng.randint(1, 6))})
            rows += own
            parted += [(*r, part) for r in own]
        g = LabeledGraph(spark.createDataFrame(parted, "src long, label string, dst long, part long"))
        n = rng.randint(2, 6)
        edges = [(k, rng.randrange(k)) for k in range(1, n) if k == 1 or rng.random() < 0.85]
        atoms = [(rng.choice(exprs), *(f"v{x}" for x in (e if rng.random() < 0.5 else e[::-1]))) for e in edges]
        names = sorted({v for a in atoms for v in a[1:]})
        q = PathQuery.of([v for v in names if rng.random() < 0.5], atoms)
        want = brute(rows, q)
        assert rows_of(ev.evaluate(q, g), q) == want, (rows, str(q))
        assert rows_of(ev.evaluate(q, g, decomposition="single"), q) == want
        if i % 4 == 0:
            assert rows_of(ev.evaluate(q, g, how=Evaluation(Scratch(spark), mode="local")), q) == want


def test_parts_with_constants(spark):
    g = LabeledGraph(spark.createDataFrame([(1, "a", 2, 0), (3, "a", 4, 1), (2, "b", 5, 0)], "src long, label string, dst long, part long"))
    for text, want in (("Y <- [a](1, Y)", {(2,)}), ("X, Z <- [a](X, 2), [b](2, Z)", {(1, 5)}), (" <- [a](9, Y)", set()), ("X <- [a](X, Y), [b](U, V)", {(1,), (3,)})):
        q = parse_query(text)
        assert rows_of(ev.evaluate(q, g), q) == want


def test_budget(spark):
    g = graph(spark, [(i, "a", i + 1) for i in range(20)])
    q = parse_query("A, C, E <- [a](O, A), [a](O, C), [a](O, E)")
    with pytest.raises(ev.BudgetError):
        ev.evaluate(q, g, how=Evaluation(Scratch(spark), budget=100.0))
    assert ev.evaluate(q, g, how=Evaluation(Scratch(spark), budget=1e9)).count() == 20
