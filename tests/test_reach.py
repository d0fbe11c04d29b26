from __future__ import annotations

import random

import pytest

from regpath.functions.regex import invert, parse_path, to_automaton
from regpath.operators import reach
from regpath.operators.components import connected_components
from regpath.operators.joins import acyclic_join
from regpath.operators.scratch import Scratch
from regpath.sources import builders
from regpath.sources.graph import LabeledGraph


def graph(spark, rows, guards=None):
    g = LabeledGraph.from_edges(spark.createDataFrame(rows, "src long, label string, dst long"))
    for name, vs in (guards or {}).items():
        g = g.with_guard(name, spark.createDataFrame([(v,) for v in vs], "v long"))
    return g


def pairs(rows, text, guards=None):
    """Pairs of an expression by a plain search."""
    a = to_automaton(parse_path(text))
    vertices = {x for u, _, v in rows for x in (u, v)}
    out = set()
    for s in vertices:
        seen, todo = {(s, 0)}, [(s, 0)]
        while todo:
            u, q = todo.pop()
            for b, x, p in a.transitions:
                if b != q:
                    continue
                if hasattr(x, "name"):
                    to = [u] if u in guards[x.name] else []
                else:
                    to = [d if not x.inverse else s_ for s_, l, d in rows if ((l in x.labels) != x.negated) and (s_ if not x.inverse else d) == u]
                for v in to:
                    if (v, p) not in seen:
                        seen.add((v, p))
                        todo.append((v, p))
        out |= {(s, v) for v, q in seen if q in a.finals}
    return out


def got(df):
    rows = [tuple(r) for r in df.collect()]
    assert len(rows) == len(set(rows))
    return set(rows)


def ones(spark, vs):
    return spark.createDataFrame([(v,) for v in vs], "v long")


TEXTS = ["a", "a/b", "(a|b)*/c", "a*", "(a/^b)*", "[g]/a*/[g]", "a?/b", ".*/!(a)", "()", "a{2,}", "(a|[g]/b)*"]


@pytest.mark.parametrize("mode", ["unrolled", "local", "rounds"])
def test_three_ways_agree_with_a_plain_search(spark, mode):
    rng = random.Random(5)
    rows = sorted({(rng.randrange(6), rng.choice("abc"), rng.randrange(6)) for _ in range(12)})
    guards = {"g": {1, 2, 4}}
    g = graph(spark, rows, guards)
    how = reach.Evaluation(Scratch(spark), mode=mode, cap=1)
    texts = [t for t in TEXTS if not to_automaton(parse_path(t)).cyclic] if mode == "unrolled" else TEXTS if mode == "local" else TEXTS[2:6]
    xs, ys = {0, 1, 2, 3}, {1, 2, 3, 5}
    for text in texts:
        e, want = parse_path(text), pairs(rows, text, guards)
        assert got(reach.pairs_capped(g, e, how=how)) == want, text
        kept = {(x, y) for x, y in want if x in xs and y in ys}
        assert got(reach.pairs_capped(g, e, [ones(spark, xs)], [ones(spark, ys)], how=how)) == kept, text
        assert got(reach.reach_unary(g, e, "x", [ones(spark, xs)], [ones(spark, ys)], how=how)) == {(x,) for x, _ in kept}, text
        assert got(reach.reach_unary(g, e, "y", [ones(spark, xs), ones(spark, [1, 2])], [ones(spark, ys)], how=how)) == {(y,) for x, y in kept if x in (1, 2)}, text
        assert got(reach.pairs_capped(g, invert(e), how=how)) == {(y, x) for x, y in want}, text
    assert got(reach.pairs_capped(g, parse_path("a"), require=False, how=how)) == set()
    assert reach.reach_nullary(g, parse_path("a/nothing"), how=how) is False


def test_capped_search_keeps_its_bounds(spark):
    for made, e in ((builders.fan_in_out(spark, 12, 12), "a/a*"), (builders.complete(spark, 6), "a+"), (builders.cycle(spark, 7), "a+"), (builders.comb(spark, 4, 2), "a+")):
        how = reach.Evaluation(Scratch(spark), mode="rounds", cap=1)
        out = got(reach.pairs_capped(made, parse_path(e), how=how))
        rows = [tuple(r) for r in made.edges.collect()]
        assert out == pairs(rows, e)
        last = [r for r in how.log if r["stage"] == "capped"][-1]
        assert last["heavy"] <= last["cap"] <= max(1, 2 * len(out) ** 0.5)
        m = len(to_automaton(parse_path(e)).transitions)
        assert last["edges_touched"] <= 4 * m * len(rows) * (last["cap"] + 1)
        assert got(reach.base_all_sources(made, parse_path(e))) == out
        assert got(reach.base_doubling(made, parse_path(e))) == out


def test_graph_sources_and_layouts(spark, tmp_path):
    (tmp_path / "t.txt").write_text("1 a 2\n2 b 3\n\n1 a 2\nbroken line here now\n")
    g = LabeledGraph.from_triples(spark, str(tmp_path / "t.txt"))
    assert g.stats() == {"vertices": 3, "edges": 2}
    assert g.stats(approx=True)["vertices"] == 3
    g.save(str(tmp_path / "g"))
    back = LabeledGraph.load(spark, str(tmp_path / "g"))
    assert got(back.edges.select("src", "label", "dst")) == {("1", "a", "2"), ("2", "b", "3")}
    plan = back.restrict(["a"]).edges._jdf.queryExecution().toString()
    assert "PartitionFilters: [isnotnull(label" in plan or "label#" in plan.split("PartitionFilters:")[1].split("]")[0]
    none = LabeledGraph.from_edges(spark.createDataFrame([(None, "a", 1), (1, "a", None), (1, None, 2)], "src long, label string, dst long"))
    assert none.edges.count() == 0
    how = reach.Evaluation(Scratch(spark))
    assert got(reach.pairs_capped(none, parse_path("a*"), how=how)) == set()
    both = graph(spark, [(1, "a", 2), (3, "b", 2)]).symmetric(materialise=True)
    assert got(reach.pairs_capped(both, parse_path("a/^b"), how=how)) == {(1, 3)}
    assert got(reach.pairs_capped(both, parse_path("./^."), how=how)) == {(1, 1), (1, 3), (3, 1), (3, 3)}


def test_files_and_directions(spark, tmp_path):
    from regpath.plans.surface import write_result

    rows = [(1, "a", 2), (2, "b", 3), (4, "a", 2)]
    for fmt in ("parquet", "orc", "json", "csv"):
        write_result(spark.createDataFrame(rows, "src long, label string, dst long"), str(tmp_path / fmt), fmt)
        g = LabeledGraph.from_files(spark, str(tmp_path / fmt), fmt, "src long, label string, dst long")
        assert got(g.edges) == set(rows)
    with pytest.raises(ValueError):
        LabeledGraph.from_files(spark, str(tmp_path / "csv"), "csv")
    for direction in ("forward", "backward", "auto"):
        how = reach.Evaluation(Scratch(spark), direction=direction)
        assert got(reach.pairs_capped(g, parse_path("a/b"), [], [ones(spark, [3])], how=how)) == {(1, 3), (4, 3)}
        assert got(reach.pairs_capped(g, parse_path("a/b?"), [ones(spark, [1])], [ones(spark, [2])], how=how)) == {(1, 2)}


def test_components(spark):
    rng = random.Random(7)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(300 + i, 301 + i) for i in range(40)] + [(500, 500 + i) for i in range(50)]
    root = {x: x for e in edges for x in e}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    df = spark.createDataFrame([*edges, (None, 1), (9, 9)], "a long, b long")
    want = {(x, find(x)) for x in root if any(x in e and e[0] != e[1] for e in edges)}
    assert got(connected_components(df)) == want
    assert connected_components(df.where("false")).count() == 0


def test_acyclic_join(spark):
    a = spark.createDataFrame([(1, 2), (1, 3), (4, 5)], "x long, y long")
    b = spark.createDataFrame([(2, 7, 0), (3, 8, 0), (9, 9, 9)], "y long, z long, w long")
    c = spark.createDataFrame([(5,), (6,)], "u long")
    assert got(acyclic_join([a, b, c], ["x", "z", "u"])) == {(1, 7, 5), (1, 7, 6), (1, 8, 5), (1, 8, 6)}
    cyclic = [spark.createDataFrame([(1, 1)], f"{p} long, {q} long") for p, q in ("xy", "yz", "zx")]
    with pytest.raises(ValueError):
        acyclic_join(cyclic, ["x"])


def test_plans_prune_and_do_not_multiply(spark, sf):
    g = builders.supply(spark, sf)
    how = reach.Evaluation(Scratch(spark))
    stored = g.stored(how.scratch)
    plan = reach.pairs_capped(stored, parse_path("placed/contains_R"), how=how)._jdf.queryExecution().toString()
    assert "In(label" in plan or "EqualTo(label" in plan
    assert "Cartesian" not in plan and "NestedLoop" not in plan and "Python" not in plan


def test_local_beyond_a_task(spark):
    """A graph without parts that is too large for one task is not walked in one, in mode local neither."""
    rows = [(i, "ab"[i % 2], (i * 7 + 3) % 40) for i in range(40)] + [(i, "a", (i * 5 + 1) % 40) for i in range(40)]
    for text, other in (("a/b", "unrolled"), ("(a|b)*/b", "rounds")):
        a, want = to_automaton(parse_path(text)), pairs(rows, text)
        for one_part, way in (((1000, 10_000), "local"), ((30, 10_000), other), ((1000, 100), other)):
            how = reach.Evaluation(Scratch(spark), mode="local", one_part=one_part)
            g = graph(spark, rows)
            assert how.way(g, a) == way
            assert got(reach.pairs_capped(g, parse_path(text), how=how)) == want


def test_pairs_by_least_middles(spark, monkeypatch):
    """Two steps with far more walks than edges: each pair once, without a shuffle of the walks; the same under filters, and within a grid."""
    rng = random.Random(5)
    rows = sorted({(s, "a", 1000 + (0 if rng.random() < 0.7 else rng.randrange(12))) for s in range(60) for _ in range(3)} | {(1000 + rng.randrange(12), "b", 2000 + rng.randrange(30)) for _ in range(200)})
    g = graph(spark, rows)
    monkeypatch.setattr(reach, "LEAST_WALKS", 1)
    monkeypatch.setattr(reach, "WALKS_FOR_MIDDLES", 0)
    for walks in (1 << 22, 40):
        monkeypatch.setattr(reach, "WALKS_A_TASK", walks)
        for text in ("a/^a", "a/b", "^b/^a", "b/^b"):
            how, want = reach.Evaluation(Scratch(spark)), pairs(rows, text)
            df = reach.pairs_capped(g, parse_path(text), how=how)
            assert got(df) == want and [x for x in how.log if x["stage"] == "middles"]
            assert "HashAggregate" not in df._jdf.queryExecution().executedPlan().toString()
        some = [*range(0, 40, 3), *range(2000, 2010)]
        kept = {p for p in pairs(rows, "a/b") if p[0] in some and p[1] in some}
        assert got(reach.pairs_capped(g, parse_path("a/b"), [ones(spark, some)], [ones(spark, some)])) == kept
