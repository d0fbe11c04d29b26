from __future__ import annotations

import random

import pytest

from regpath.plans import structure as st
from regpath.plans.query import CyclicQueryError, PathQuery, parse_query
from regpath.plans.workloads import TEXTS, workload


def random_query(rng, most=7):
    n = rng.randint(2, most)
    edges = [(i, rng.randrange(i)) for i in range(1, n) if i == 1 or rng.random() < 0.9]
    atoms = [(rng.choice("abc"), *(f"v{x}" for x in (e if rng.random() < 0.5 else e[::-1]))) for e in edges]
    names = sorted({v for a in atoms for v in a[1:]})
    return PathQuery.of([v for v in names if rng.random() < 0.5], atoms)


def test_elimination_is_confluent():
    rng = random.Random(1)
    for _ in range(200):
        q = random_query(rng)
        graphs = [st.elimination_order(q, p)[1] for p in ("leaves_first", "paths_first", "random", rng.sample(list(q.vars), len(q.vars)))]
        assert all(g == graphs[0] for g in graphs)
        assert all(sum(graphs[0][v].values()) >= 3 for v in graphs[0] if v not in q.free)


def test_widths_of_the_examples():
    nine = workload("nine_atoms")
    assert sorted(st.promoted(nine)) == ["B", "F"]
    assert all(sum(st.contracted_graph(nine)[v].values()) == 3 for v in "BF")
    assert st.promoted(nine.induced("ACE")) == ["B"] and st.promoted(nine.induced("AGH")) == ["F"]
    assert (st.ctw(nine), st.fhtw(nine)) == (1, 3)
    for n in range(3, 7):
        star = PathQuery.of([f"L{i}" for i in range(n)], [("a", "M", f"L{i}") for i in range(n)])
        assert (st.ctw(star), st.fhtw(star)) == (1, n)
    for k in range(2, 6):
        atoms = [("a", f"P{i}", f"P{i + 1}") for i in range(k)]
        ends, inner = PathQuery.of(["P0", f"P{k}"], atoms), PathQuery.of([f"P{i}" for i in range(1, k)], atoms)
        assert (st.ctw(ends), st.fhtw(ends)) == (0, 2)
        assert (st.ctw(inner), st.fhtw(inner)) == (0, 1)
    comb = PathQuery.of(["X", "Y", "A", "B", "C"], [("a", "X", "p"), ("a", "p", "q"), ("a", "q", "r"), ("a", "r", "Y"), ("a", "p", "A"), ("a", "q", "B"), ("a", "r", "C")])
    assert (st.ctw(comb), st.fhtw(comb)) == (3, 5)


def test_canonical_decompositions_are_valid_and_least():
    rng = random.Random(2)
    for _ in range(200):
        q = random_query(rng)
        d = st.canonical_decomposition(q)
        d.validate(q)
        single = st.Decomposition((frozenset(q.head), frozenset(q.vars)), ((0, 1),))
        single.validate(q)
        assert st.ctw(q) <= st.ctw_of(q, single)
        if st.is_free_connex(q):
            assert st.ctw(q) == 0
        # bags merged at random stay a decomposition, of no less width
        bags, edges = list(d.bags), list(d.edges)
        core = d.free_core(q)
        inside = [e for e in edges if e[0] in core and e[1] in core]
        if inside:
            a, b = rng.choice(inside)
            bags[a] = bags[a] | bags[b]
            merged = st.Decomposition(tuple(bags), tuple(edges))
            merged.validate(q)
            assert st.ctw(q) <= st.ctw_of(q, merged)


def test_decompositions_without_a_core_are_rejected():
    q = parse_query("A, C, E <- [a](O, A), [b](O, C), [c](O, E)")
    with pytest.raises(ValueError):
        st.Decomposition((frozenset("AC"), frozenset("CE"), frozenset("OACE")), ((0, 2), (1, 2))).validate(q)
    with pytest.raises(ValueError):
        st.Decomposition((frozenset("ACE"), frozenset("OAC")), ((0, 1),)).validate(q)
    with pytest.raises(ValueError):
        st.Decomposition((frozenset("ACE"), frozenset("OA"), frozenset("OCE")), ((0, 1), (0, 2))).validate(q)


def test_the_four_bags_of_the_running_query():
    q = workload("nine_atoms")
    d = st.Decomposition((frozenset("ABCDE"), frozenset("ACE"), frozenset("AGH"), frozenset("AFGHIJ")), ((0, 1), (1, 2), (2, 3)))
    d.validate(q)
    assert st.ctw_of(q, d) == 1


def test_cyclic_queries():
    for text in ("X <- [a](X, Y), [b](Y, Z), [c](Z, X)", "X <- [a](X, Y), [b](Y, X)", "X <- [a](X, X)"):
        with pytest.raises(CyclicQueryError):
            st.check_acyclic(parse_query(text))
    st.check_acyclic(parse_query("X <- [a](X, Y), [b](U, V)"))


def test_join_trees_have_free_atoms_on_top():
    rng = random.Random(3)
    seen = 0
    for _ in range(400):
        q = random_query(rng)
        if not st.is_free_connex(q):
            continue
        for atoms in st.trees(q):
            tops = [a for a in atoms if a.ends & q.free] or atoms
            for root in tops:
                tree = st.free_top_join_tree(q, atoms, root)
                assert len(tree.order) == len(atoms) and st.is_free_top(q, tree)
                seen += 1
    assert seen > 300


def test_query_text():
    q = parse_query("X, Y <- [a/(b|c)*/'x]y'](X, Z), [[g]/a](Z, Y), [a](Z, 'C1'), [a](Z, 17)")
    assert q.head == ("X", "Y") and q.constants == {"const0": "C1", "const1": 17} and len(q.atoms) == 4
    for bad in ("X [a](X, Y)", "X <- a(X, Y)", "W <- [a](X, Y)", "X, X <- [a](X, Y)", "X <- [a](X, x)"):
        with pytest.raises(ValueError):
            parse_query(bad)
    for name in TEXTS:
        st.check_acyclic(workload(name))
