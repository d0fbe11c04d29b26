"""The library's queries on the given tables, each with SQL of its own."""

from __future__ import annotations

import itertools
from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.functions import regex, vectorised
from regpath.operators import reach
from regpath.plans import evaluate as ev
from regpath.plans import measure, surface, workloads
from regpath.plans import structure as st
from regpath.plans.query import PathQuery, parse_query
from regpath.plans.sql import GRAPHS as G
from regpath.plans.sql import closure, conjunction, edge, query, then
from regpath.sources import builders
from regpath.sources.builders import graph_from_tables, read
from regpath.sources.graph import LabeledGraph
from regpath.streaming import feed

Run = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Run] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, run: Run, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql is not None:
        ORACLES[name] = sql


def _stored(spark: SparkSession, sf_dir: str, graph: str, **how) -> tuple[LabeledGraph, reach.Evaluation]:
    """The graph written once, and an evaluation that writes beside it."""
    g = graph_from_tables(spark, sf_dir, graph)
    e = ev.new_evaluation(g, **how)
    return g.stored(e.scratch), e


# ---- graphs


def _graph(name: str) -> Run:
    return lambda spark, d: graph_from_tables(spark, d, name).edges.select("src", "label", "dst")


for _name in G:
    _add(f"graph_{_name}", _graph(_name), query(_name, "SELECT src, label, dst FROM g"))
_add("graph_vertices", lambda s, d: builders.supply(s, d).vertices(), query("supply", "SELECT v FROM n"))
_add("graph_symmetric", lambda s, d: builders.talk(s, d).symmetric(materialise=True).edges.select("src", "label", "dst"), query("talk", "SELECT src, label, dst FROM g UNION SELECT dst, '^' || label, src FROM g"))
_add("graph_label_stats", lambda s, d: builders.supply(s, d).label_stats(), query("supply", "SELECT label, count(*) AS edges, count(DISTINCT src) AS sources, count(DISTINCT dst) AS targets FROM g GROUP BY label"))
_add(
    "graph_degree_topk", lambda s, d: surface.top_k(builders.supply(s, d).edges.groupBy("src", "label").agg(F.count(F.lit(1)).alias("degree")), [F.desc("degree"), "src", "label"], 20),
    query("supply", "SELECT src, label, count(*) AS degree FROM g GROUP BY src, label ORDER BY degree DESC, src, label LIMIT 20"),
)


# ---- one expression


def _rpq(graph: str, text: str, **how) -> Run:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, graph, **how)
        return reach.pairs_capped(g, regex.parse_path(text), how=e)

    return run


def _pairs(graph: str, select: str, *tables) -> str:
    return query(graph, f"SELECT DISTINCT x, y FROM ({select})", *tables)


_add("rpq_symbol", _rpq("supply", "contains_R"), _pairs("supply", edge("contains_R")))
_add("rpq_concat", _rpq("supply", "placed/contains_R"), _pairs("supply", then("a", "b"), ("a", edge("placed")), ("b", edge("contains_R"))))
_add("rpq_union", _rpq("supply", "c_in|s_in/part_of"), _pairs("supply", f"{edge('c_in')} UNION {then('a', 'b')}", ("a", edge("s_in")), ("b", edge("part_of"))))
_add("rpq_star", _rpq("timeline", "(view|click)*"), _pairs("timeline", "SELECT * FROM c", closure("c", "view", "click")))
_add("rpq_plus", _rpq("talk", "(user/assistant)+"), _pairs(
    "talk", "SELECT * FROM p", ("ua", then("a", "b")), "p(x, y) AS (SELECT x, y FROM ua UNION SELECT p.x, ua.y FROM p JOIN ua ON p.y = ua.x)", ("a", edge("user")), ("b", edge("assistant")),
))
_add("rpq_optional", _rpq("timeline", "purchase?/error"), _pairs("timeline", f"SELECT * FROM b UNION {then('a', 'b')}", ("a", edge("purchase")), ("b", edge("error"))))
_add("rpq_repeat", _rpq("timeline", "(view|click){1,3}"), _pairs("timeline", f"SELECT * FROM a UNION {then('a', 'a')} UNION {then('a', 'a', 'a')}", ("a", edge("view", "click"))))
_add("rpq_inverse", _rpq("supply", "contains_R/^contains_R"), _pairs("supply", then("a", "b"), ("a", edge("contains_R")), ("b", edge("contains_R", back=True))))
_add("rpq_any_label", _rpq("timeline", ".*"), _pairs("timeline", "SELECT * FROM c", closure("c")))
_add("rpq_negated", _rpq("timeline", "!(view|click)/!(error)"), _pairs("timeline", then("a", "b"), ("a", edge("purchase", "error", "signup")), ("b", edge("view", "click", "purchase", "signup"))))
_add("rpq_epsilon", _rpq("talk", "()"), query("talk", "SELECT v AS x, v AS y FROM n"))
_add("rpq_cyclic_star", _rpq("hop", "purchase*"), _pairs("hop", "SELECT * FROM c", closure("c", "purchase")))
_add("rpq_cyclic_any", _rpq("hop", ".*"), _pairs("hop", "SELECT * FROM c", closure("c")))


def _reversed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Walks of the reversed expression over reversed edges, turned round: the same pairs."""
    g, e = _stored(spark, sf_dir, "timeline")
    turned = LabeledGraph(g.edges.withColumns({"src": F.col("dst"), "dst": F.col("src")}))
    found = reach.pairs_capped(turned, regex.reverse(regex.parse_path("(view|click)*/purchase")), how=e)
    return found.select(F.col("y").alias("x"), F.col("x").alias("y"))


def _guarded(spark: SparkSession, sf_dir: str) -> DataFrame:
    g, e = _stored(spark, sf_dir, "timeline")
    g = g.with_guard("before_signup", reach.reach_unary(g, regex.parse_path("signup"), "x", how=e))
    return reach.pairs_capped(g, regex.parse_path("(view|click)*/[before_signup]/.*/error"), how=e)


_add("rpq_reverse", _reversed, _pairs("timeline", then("c", "b"), closure("c", "view", "click"), ("b", edge("purchase"))))
_add("rpq_guard", _guarded, _pairs("timeline", then("c", "m", "d", "b"), closure("c", "view", "click"), ("m", "SELECT DISTINCT src AS x, src AS y FROM g WHERE label = 'signup'"), closure("d"), ("b", edge("error"))))


def _unary(keep: str) -> Run:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, "timeline")
        x_in = reach.reach_unary(g, regex.parse_path("click"), "x", how=e)
        y_in = reach.reach_unary(g, regex.parse_path("error"), "x", how=e)
        return reach.reach_unary(g, regex.parse_path(".*/purchase"), keep, [x_in], [y_in], how=e)

    return run


_ends = ("r", then("c", "b")), closure("c"), ("b", edge("purchase"))
_within = "x IN (SELECT src FROM g WHERE label = 'click') AND y IN (SELECT src FROM g WHERE label = 'error')"
_add("reach_keep_source", _unary("x"), query("timeline", f"SELECT DISTINCT x AS v FROM r WHERE {_within}", *_ends))
_add("reach_keep_target", _unary("y"), query("timeline", f"SELECT DISTINCT y AS v FROM r WHERE {_within}", *_ends))


def _nullary(spark: SparkSession, sf_dir: str) -> DataFrame:
    g, e = _stored(spark, sf_dir, "timeline")
    texts = ["purchase/purchase/purchase", "signup/nothing", ".*/error"]
    rows = [(t, reach.reach_nullary(g, regex.parse_path(t), how=e)) for t in texts]
    return spark.createDataFrame(rows, "expression string, answer boolean")


_add("reach_nullary", _nullary, query(
    "timeline", "SELECT 'purchase/purchase/purchase' AS expression, EXISTS (SELECT 1 FROM p a JOIN p b ON a.y = b.x JOIN p c ON b.y = c.x) AS answer UNION ALL SELECT 'signup/nothing', EXISTS (SELECT 1 FROM g WHERE label = 'nothing') UNION ALL SELECT '.*/error', EXISTS (SELECT 1 FROM g WHERE label = 'error')", ("p", edge("purchase")),
))
_purchases = _pairs("hop", "SELECT * FROM c", closure("c", "purchase"))
_add("pairs_capped_auto", _rpq("hop", "purchase*", mode="rounds"), _purchases)
_add("pairs_capped_tiny_cap", _rpq("hop", "purchase*", mode="rounds", cap=2), _purchases)

# no parts, and too many pairs for a task: what runs is the capped search
_add("pairs_beyond_parts", _rpq("supply", "(placed/contains_R/supplied_by/s_in/part_of)+"), _pairs("supply", then("a", "b", "c", "d", "f"), ("a", edge("placed")), ("b", edge("contains_R")), ("c", edge("supplied_by")), ("d", edge("s_in")), ("f", edge("part_of"))))


def _gadget(make: Callable[[SparkSession], LabeledGraph], text: str) -> Run:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = make(spark)
        return reach.pairs_capped(g, regex.parse_path(text), how=ev.new_evaluation(g, mode="rounds"))

    return run


# made graphs: all sources heavy, one heavy source, long walks of few pairs
_add("gadget_fan", _gadget(lambda s: builders.fan_in_out(s, 150, 150), "a+"), "SELECT a + 1 AS x, b + 151 AS y FROM range(150) i(a), range(150) j(b) UNION ALL SELECT a + 1, 0 FROM range(150) i(a) UNION ALL SELECT 0, b + 151 FROM range(150) j(b)")
_add("gadget_one_heavy", _gadget(lambda s: builders.fan_in_out(s, 1, 400), "a/a"), "SELECT 1 AS x, b + 2 AS y FROM range(400) j(b)")


def _one(base: Callable) -> Run:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, "hop")
        return base(g, regex.parse_path("purchase*"), e)

    return run


_add("pairs_all_sources", _one(reach.base_all_sources), _purchases)
_add("pairs_doubling", _one(reach.base_doubling), _purchases)


# ---- whole queries


def _evaluated(name: str, mode: str = "auto", **how) -> Run:
    graph = workloads.TEXTS[name][0]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, graph, mode=mode)
        return ev.evaluate(workloads.workload(name), g, how=e, **how)

    return run


def _connex(name: str, **how) -> Run:
    graph = workloads.TEXTS[name][0]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, graph)
        return ev.eval_free_connex(workloads.workload(name), g, how=e, **how)

    return run


def _based(name: str, base: Callable, **how) -> Run:
    graph = workloads.TEXTS[name][0]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, graph)
        return base(workloads.workload(name), g, e, **how)

    return run


_all, _vc, _vp, _es = closure("c"), closure("vc", "view", "click"), closure("vp", "view", "purchase"), closure("es", "error", "signup")
_four = [_all, ("r1", then("c", "p")), ("p", edge("purchase")), ("er", edge("error")), ("si", edge("signup")), ("cl", edge("click"))]
_four_atoms = [("r1", "X", "Y"), ("er", "Y", "Z"), ("si", "Z", "W"), ("cl", "X", "U")]
FOUR = query("timeline", conjunction(["X", "Y", "U"], _four_atoms), *_four)
FULL = query("timeline", conjunction(["X", "Y", "Z", "W", "U"], _four_atoms), *_four)
_five = [("pc", then("pl", "cr")), ("pl", edge("placed")), ("cr", edge("contains_R")), ("sb", edge("supplied_by")), ("si", edge("s_in")), ("ss", then("sb", "si")), ("ci", edge("c_in")), ("po", edge("part_of")), ("ca", edge("contains_A")), ("cn", edge("contains_N"))]
FIVE = query("supply", conjunction(["A", "B", "D"], [("pc", "A", "B"), ("ss", "B", "C"), ("sb", "B", "D"), ("ci", "A", "E"), ("po", "E", "F")]), *_five)
# the nine atoms: what hangs on F is one table, and so is what hangs on B, to keep the join small
_nine = [
    _all, _vc, _vp, _es, ("pu", edge("purchase")), ("cl", edge("click")), ("er", edge("error")), ("si", edge("signup")), ("r1", then("vc", "pu")), ("r5", then("es", "cl")),
    ("ok", "SELECT DISTINCT c.x AS f FROM c JOIN er ON c.y = er.x JOIN si ON er.y = si.x"),
    ("be", "SELECT DISTINCT vc.x AS b, vp.x AS e FROM vc JOIN vp ON vc.y = vp.y"),
    ("lt", "SELECT DISTINCT r1.x AS a, vc.y AS c, be.e FROM r1 JOIN vc ON r1.y = vc.x JOIN be ON r1.y = be.b"),
    ("rt", "SELECT DISTINCT r5.x AS a, es.y AS g, vp.y AS h FROM r5 JOIN ok ON r5.y = ok.f JOIN es ON r5.y = es.x JOIN vp ON r5.y = vp.x"),
]
NINE = query("timeline", "SELECT DISTINCT lt.a AS A, lt.c AS C, lt.e AS E, rt.g AS G, rt.h AS H FROM lt JOIN rt ON lt.a = rt.a", *_nine)
_k = [("pl", "A", "B"), ("cr", "B", "C"), ("sb", "C", "D"), ("si", "D", "E"), ("po", "E", "F")]


def _path(k: int) -> str:
    return query("supply", conjunction(["A", "ABCDEF"[k]], _k[:k]), *_five)


STAR3 = query("supply", conjunction(["A", "C", "E"], [("pl", "A", "B"), ("cr", "B", "C"), ("ca", "B", "E")]), *_five)
STAR4 = query("supply", conjunction(["A", "C", "E", "F"], [("pl", "A", "B"), ("cr", "B", "C"), ("ca", "B", "E"), ("cn", "B", "F")]), *_five)
DANGLING = query("timeline", conjunction(["X", "Y", "U"], [("p", "X", "Y"), ("c", "Y", "U"), ("ss", "U", "W")]), _all, ("p", edge("purchase")), ("s", edge("signup")), ("ss", then("s", "s")))
LEAF = query("supply", conjunction(["X"], [("pl", "X", "Y"), ("cr", "Y", "Z")]), *_five)
FOREST = query("supply", conjunction(["X", "U"], [("po", "X", "Y"), ("si", "U", "V")]), *_five)

_add("fc_four_atoms", _connex("four_atoms"), FOUR)
_add("fc_five_atoms", _connex("five_atoms"), FIVE)
_add("fc_full", _connex("full"), FULL)
_add("fc_boolean", _connex("boolean"), query("timeline", "SELECT EXISTS (SELECT 1 FROM r1 JOIN er ON r1.y = er.x) AS answer", *_four))
_add("fc_forest", _connex("forest"), FOREST)
_add("fc_dangling_calibrated", _connex("dangling"), DANGLING)
_add("fc_dangling_literal", _connex("dangling", child_filters=False), DANGLING)


_add("acyclic_four_atoms", _evaluated("four_atoms"), FOUR)
_add("acyclic_dangling", _evaluated("dangling"), DANGLING)
_add("acyclic_boolean", _evaluated("boolean"), ORACLES["fc_boolean"])


def _other_root(spark: SparkSession, sf_dir: str) -> DataFrame:
    g, e = _stored(spark, sf_dir, "timeline")
    q = workloads.workload("four_atoms")
    return ev.eval_free_connex(q, g, root=q.atoms[3], how=e)


_add("fc_other_root", _other_root, FOUR)


def _messages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of all upward messages, parent projections and relations of the four-atom query."""
    g, e = _stored(spark, sf_dir, "timeline")
    q, kept = workloads.workload("four_atoms"), []
    ev.eval_free_connex(q, g, how=e, keep=kept)
    number = {a: i + 1 for i, a in enumerate(q.atoms)}
    rows = []
    for tree, m in kept:
        rows += [(f"B{number[a]}-{number[tree.parent[a]]}", df.count()) for a, df in m.up.items()]
        rows += [(f"T{number[tree.parent[a]]}-{number[a]}", df.count()) for a, df in m.down.items()]
        rows += [(f"R{number[a]}", df.count()) for a, df in m.relations.items()]
    return spark.createDataFrame(rows, "message string, n long")


_add("fc_messages", _messages, query(
    "timeline",
    "SELECT 'B3-2' AS message, (SELECT count(*) FROM b3) AS n UNION ALL SELECT 'B2-1', (SELECT count(*) FROM b2) UNION ALL SELECT 'B4-1', (SELECT count(*) FROM b4) UNION ALL SELECT 'R1', (SELECT count(*) FROM f1) "
    "UNION ALL SELECT 'T1-2', (SELECT count(DISTINCT y) FROM f1) UNION ALL SELECT 'T1-4', (SELECT count(DISTINCT x) FROM f1) UNION ALL SELECT 'R2', (SELECT count(DISTINCT y) FROM f1 WHERE y IN (SELECT v FROM b2)) UNION ALL SELECT 'R4', (SELECT count(*) FROM cl WHERE x IN (SELECT x FROM f1))",
    *_four, ("b3", "SELECT DISTINCT x AS v FROM si"), ("b2", "SELECT DISTINCT x AS v FROM er WHERE y IN (SELECT v FROM b3)"), ("b4", "SELECT DISTINCT x AS v FROM cl"), ("f1", "SELECT * FROM r1 WHERE y IN (SELECT v FROM b2) AND x IN (SELECT v FROM b4)"),
))


def _joined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Materialised relations of three columns and two, whole tables (customers without orders dangle), joined the classical way."""
    from regpath.operators.joins import acyclic_join

    o = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("o"), F.col("o_custkey").alias("c"), F.col("o_orderstatus").alias("s"))
    line = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o"), F.col("l_partkey").alias("p")).distinct()
    c = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("c"), F.col("c_nationkey").alias("n"))
    return acyclic_join([line, o, c], ["p", "o", "s", "n"])


_add("acyclic_join", _joined, "SELECT DISTINCT l_partkey AS p, o_orderkey AS o, o_orderstatus AS s, c_nationkey AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey")


# ---- contraction


def _contracted(text: str, graph: str, **how) -> Run:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, graph)
        return ev.evaluate(parse_query(text), g, decomposition="single", how=e, **how)

    return run


_tl = [("vi", edge("view")), ("er", edge("error")), ("cl", edge("click"))]
for _n, _text, _atoms in (
    ("out_in", "A, C <- [view](B, A), [error](B, C)", [("vi", "B", "A"), ("er", "B", "C")]),
    ("in_out", "A, C <- [view](A, B), [error](B, C)", [("vi", "A", "B"), ("er", "B", "C")]),
    ("in_in", "A, C <- [view](A, B), [view](C, B)", [("vi", "A", "B"), ("vi", "C", "B")]),
    ("out_out", "A, C <- [error](C, B), [view](B, A)", [("er", "C", "B"), ("vi", "B", "A")]),
):
    _add(f"contract_splice_{_n}", _contracted(_text, "timeline"), query("timeline", conjunction(["A", "C"], _atoms), *_tl))
# a timeline's vertex has one successor: an order has many, so both atoms that leave B meet here
_add("contract_splice_out_in_orders", _contracted("A, C <- [contains_A](B, A), [contains_R](B, C)", "supply"), query("supply", conjunction(["A", "C"], [("ca", "B", "A"), ("cr", "B", "C")]), *_five))
_add("contract_leaf_forward", _contracted("A, B <- [view](A, B), [error](B, C)", "timeline"), query("timeline", conjunction(["A", "B"], [("vi", "A", "B"), ("er", "B", "C")]), *_tl))
_add("contract_leaf_backward", _contracted("A, B <- [view](A, B), [error](C, A)", "timeline"), query("timeline", conjunction(["A", "B"], [("vi", "A", "B"), ("er", "C", "A")]), *_tl))
_add("contract_composite_leaf", _evaluated("composite_leaf", order=["Y", "Z"]), LEAF)
_add("contract_leaf_first", _evaluated("composite_leaf", order=["Z", "Y"]), LEAF)
_add("contract_vanished_component", _contracted("A <- [view](A, B), [purchase/purchase](P, Q)", "timeline"), query(
    "timeline", "SELECT DISTINCT x AS A FROM vi WHERE EXISTS (SELECT 1 FROM pu a JOIN pu b ON a.y = b.x)", *_tl, ("pu", edge("purchase")),
))
_add("contract_all_guards", _evaluated("nine_atoms", skip_trivial_guards=False), NINE)


# ---- decompositions

_add("acyclic_running_query", _evaluated("nine_atoms"), NINE)
_add("acyclic_running_tables", _evaluated("nine_atoms", mode="local"), NINE)
_add("acyclic_running_single_tables", _evaluated("nine_atoms", mode="local", decomposition="single"), NINE)
_add("acyclic_running_single_bag", _evaluated("nine_atoms", decomposition="single"), NINE)
_add("acyclic_star2", _evaluated("star2"), _path(2))
_add("acyclic_star3", _evaluated("star3"), STAR3)
_add("acyclic_star4", _evaluated("star4"), STAR4)
for _i in range(1, 6):
    _add(f"path_k{_i}", _evaluated(f"path_k{_i}"), _path(_i))
_add("path_join_vars_free", _evaluated("path_join_vars_free"), query("supply", conjunction(["B", "C"], _k[:3]), *_five))
_add("path_replaced_atom", _evaluated("replaced_atom"), query("timeline", conjunction(["X", "Y", "U"], [("c", "X", "M"), ("an", "M", "N"), ("p", "N", "Y"), *_four_atoms[1:]]), *_four, ("an", edge())))




def _decomposed(name: str, bags: list[str], edges: list[tuple[int, int]]) -> Run:
    """A workload by a decomposition of our own."""
    d = st.Decomposition(tuple(frozenset(b) for b in bags), tuple(edges))
    return _evaluated(name, mode="local", decomposition=d)


_add("decomposition_given", _decomposed("nine_atoms", ["ABCDE", "ACE", "AGH", "AFGHIJ"], [(0, 1), (1, 2), (2, 3)]), NINE)
_add("decomposition_redundant_bags", _decomposed("star3", ["ACE", "ACE", "AC", "ABCE", "BC"], [(0, 1), (1, 2), (0, 3), (3, 4)]), STAR3)


def _without_free(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A bag without free variables is a truth value only."""
    g, e = _stored(spark, sf_dir, "timeline", mode="local")
    q = parse_query("A <- [view](A, B), [purchase](P, Q), [purchase](Q, R)")
    d = st.Decomposition((frozenset("A"), frozenset("AB"), frozenset("PQ"), frozenset("QR")), ((0, 1), (1, 2), (2, 3)))
    return ev.evaluate(q, g, decomposition=d, how=e)


_add("decomposition_bag_without_free", _without_free, query("timeline", "SELECT DISTINCT x AS A FROM vi WHERE EXISTS (SELECT 1 FROM pu a JOIN pu b ON a.y = b.x)", *_tl, ("pu", edge("purchase"))))


# ---- structure: of the queries that the contents of orders form


def _order_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(body, lines, orders): each form that an order's contents have, as a query, and the orders of that form.

    A line leads from the order to its part, and from the part to its supplier; both are named by the first line that has them.
    """
    line = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    own = line.repartition("l_orderkey").sortWithinPartitions("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    return own.mapInArrow(_forms, "body string, lines long, n long").groupBy("body", "lines").agg(F.sum("n").alias("orders"))


def _forms(batches):
    """Forms of orders, whose lines stand together, and how many of each batch have them."""
    held = None
    for batch in itertools.chain(batches, [None]):
        rows = held if batch is None else np.stack([batch.column(i).to_numpy() for i in (0, 2, 3)], axis=1)
        if batch is not None:
            rows = rows if held is None else np.concatenate([held, rows])
            cut = np.flatnonzero(rows[1:, 0] != rows[:-1, 0])  # the last order may go on in the next batch
            rows, held = np.split(rows, [cut[-1] + 1 if len(cut) else 0])
        if rows is None or not len(rows):
            continue
        start = np.flatnonzero(np.concatenate([[True], rows[1:, 0] != rows[:-1, 0]]))
        lines = np.diff(np.append(start, len(rows)))
        found = []
        for n in np.unique(lines):
            own = rows[start[lines == n][:, None] + np.arange(n)]
            # the first line with each line's part, and with its supplier
            first = np.concatenate([(own[:, :, None, c] == own[:, None, :, c]).argmax(axis=2) for c in (1, 2)], axis=1) + 1
            for f, many in zip(*np.unique(first, axis=0, return_counts=True), strict=True):
                found.append((", ".join(f"[contains](O, P{p}), [supplied_by](P{p}, S{s})" for p, s in zip(f[:n], f[n:], strict=True)), int(n), int(many)))
        yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in found], k) for c, k in enumerate((pa.string(), pa.int64(), pa.int64()))], names=["body", "lines", "n"])


def _of_forms(schema: str, analyse: Callable[[str, int], list[tuple]]) -> Run:
    """What is found of each form, beside its orders; the forms are read and analysed in Spark's tasks."""

    def rows(batches):
        for b in batches:
            found = [(*r, int(orders)) for body, lines, orders in zip(b.body, b.lines, b.orders, strict=True) for r in analyse(body, int(lines))]
            yield pd.DataFrame(found, columns=[c.split()[0] for c in schema.split(", ")] + ["orders"])

    return lambda spark, sf_dir: _order_queries(spark, sf_dir).mapInPandas(rows, f"{schema}, orders long")


def _acyclic(body: str, head: list[str]) -> list[PathQuery]:
    """The query of a form, or none if it is cyclic."""
    q = parse_query(f"O <- {body}")
    try:
        st.check_acyclic(q)
    except st.CyclicQueryError:
        return []
    return [q.with_head(head)]


def _numbered(letter: str, lines: int) -> list[str]:
    return [f"{letter}{i + 1}" for i in range(lines)]


def _listed(variables) -> str:
    return " ".join(sorted(variables, key=lambda v: (v[0], int(v[1:] or 0))))


def _forms_sql(body: str) -> str:
    """A statement over forms (body, lines, parts, suppliers, orders), and forms without a cycle, `trees`: no part and no supplier stands in two lines."""
    of_line = "list_position(ps, ps[i])"
    return f"""WITH own AS (SELECT l_orderkey, list(l_partkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS ps, list(l_suppkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS ss FROM lineitem GROUP BY l_orderkey),
forms AS (SELECT array_to_string(['[contains](O, P' || {of_line} || '), [supplied_by](P' || {of_line} || ', S' || list_position(ss, ss[i]) || ')' for i in range(1, len(ps) + 1)], ', ') AS body,
  CAST(len(ps) AS BIGINT) AS lines, len(list_distinct(ps)) AS parts, len(list_distinct(ss)) AS suppliers, count(*) AS orders FROM own GROUP BY ALL),
trees AS (SELECT lines, orders, ['P' || i for i in range(1, lines + 1)] AS p, ['S' || i for i in range(1, lines + 1)] AS s FROM forms WHERE parts = lines AND suppliers = lines)
{body}"""


def _widths(body: str, n: int) -> list[tuple]:
    """Both widths, with all suppliers free."""
    return [(n, st.ctw(q), st.fhtw(q), st.is_free_connex(q)) for q in _acyclic(body, _numbered("S", n))]


_add("width_table", _of_forms("lines long, ctw long, fhtw long, free_connex boolean", _widths), _forms_sql("SELECT lines, CAST(lines >= 3 AS BIGINT) AS ctw, lines AS fhtw, lines = 1 AS free_connex, orders FROM trees"))


def _eliminations(body: str, n: int) -> list[tuple]:
    """Bound variables that each policy takes out, with all suppliers free and with the first."""
    rows = []
    for bag, free in (("all", n), ("first", 1)):
        for q in _acyclic(body, _numbered("S", free)):
            for policy in ("leaves_first", "paths_first", "random"):
                order, g = st.elimination_order(q, policy)
                rows.append((n, bag, policy, _listed(order), _listed(v for v in g if v not in q.free)))
    return rows


_add("elimination_trace", _of_forms("lines long, bag string, policy string, taken string, bound_left string", _eliminations), _forms_sql(
    "SELECT lines, bag, policy, taken, bound_left, orders FROM (SELECT lines, 'all' AS bag, CASE WHEN lines <= 2 THEN 'O ' ELSE '' END || array_to_string(p, ' ') AS taken, CASE WHEN lines <= 2 THEN '' ELSE 'O' END AS bound_left, orders FROM trees "
    "UNION ALL SELECT lines, 'first', 'O ' || array_to_string(p || s[2:], ' '), '', orders FROM trees), (VALUES ('leaves_first'), ('paths_first'), ('random')) v(policy)",
))


def _decompositions(body: str, n: int) -> list[tuple]:
    """Bags of the canonical decomposition, for suppliers and for the order with its suppliers."""
    rows = []
    for head, free in (("suppliers", []), ("order", ["O"])):
        for q in _acyclic(body, [*free, *_numbered("S", n)]):
            d = st.canonical_decomposition(q)
            d.validate(q)
            rows += [(n, head, _listed(b), i in d.free_core(q), len([v for v in st.promoted(q.induced(b)) if v not in b])) for i, b in enumerate(d.bags)]
    return rows


_add("decomposition_table", _of_forms("lines long, head string, bag string, core boolean, promoted long", _decompositions), _forms_sql(
    "SELECT lines, 'suppliers' AS head, array_to_string(s, ' ') AS bag, true AS core, CAST(lines >= 3 AS BIGINT) AS promoted, orders FROM trees UNION ALL SELECT lines, 'suppliers', 'O ' || array_to_string(p || s, ' '), false, 0, orders FROM trees "
    "UNION ALL SELECT lines, 'order', 'O ' || unnest(s), true, 0, orders FROM trees UNION ALL SELECT lines, 'order', 'O ' || unnest(p) || ' ' || unnest(s), false, 0, orders FROM trees",
))


def _join_trees(body: str, n: int) -> list[tuple]:
    """Each atom's parent, with the order and its parts free."""
    rows = []
    for q in _acyclic(body, ["O", *_numbered("P", n)]):
        tree = st.free_top_join_tree(q)
        rows += [(n, q.atoms.index(a) + 1, q.atoms.index(tree.parent[a]) + 1 if a in tree.parent else 0, tree.via.get(a, "")) for a in tree.order]
    return rows


_add("join_tree_table", _of_forms("lines long, atom long, parent long, via string", _join_trees), _forms_sql(
    "SELECT lines, 2 * i - 1 AS atom, CASE WHEN i > 1 THEN 1 ELSE 0 END::BIGINT AS parent, CASE WHEN i > 1 THEN 'O' ELSE '' END AS via, orders FROM (SELECT lines, orders, unnest(range(1, lines + 1)) AS i FROM trees) UNION ALL SELECT lines, 2 * i, 2 * i - 1, 'P' || i, orders FROM (SELECT lines, orders, unnest(range(1, lines + 1)) AS i FROM trees)",
))


_add("cyclic_rejected", _of_forms("body string, lines long, rejected boolean", lambda body, n: [(body, n, not _acyclic(body, ["O"]))]), _forms_sql("SELECT body, lines, parts < lines OR suppliers < lines AS rejected, orders FROM forms"))


# ---- baselines

_add("base_materialise", _based("four_atoms", ev.base_materialise), FOUR)
_add("base_materialise_five", _based("five_atoms", ev.base_materialise), FIVE)
_add("base_materialise_star", _based("star3", ev.base_materialise), STAR3)
_add("base_materialise_os", _based("star3", ev.base_materialise, output_sensitive=True, limit=2), STAR3)
_add("base_hypertree", _based("star3", ev.base_hypertree), STAR3)
_add("base_hypertree_four", _based("four_atoms", ev.base_hypertree), FOUR)
_add("base_no_contraction", _evaluated("star3", contract_first=False), STAR3)
_add("base_single_bag", _evaluated("star4", decomposition="single"), STAR4)


def _brute(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All maps of three variables on the graph of nations and regions."""
    g, e = _stored(spark, sf_dir, "supply")
    return ev.base_bruteforce(parse_query("X, Z <- [part_of](X, Y), [part_of](Z, Y)"), g.restrict(["part_of"]), e)


_add("base_bruteforce", _brute, query("supply", conjunction(["X", "Z"], [("po", "X", "Y"), ("po", "Z", "Y")]), *_five))


# ---- measures


def _out_and_rpqs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the result and of each atom's expression alone."""
    g, e = _stored(spark, sf_dir, "timeline")
    q = workloads.workload("four_atoms")
    rows = [("OUT", ev.eval_free_connex(q, g, how=e).count())] + [(f"r{i + 1}", reach.pairs_capped(g, a.expr, how=e).count()) for i, a in enumerate(q.atoms)]
    return spark.createDataFrame(rows, "relation string, n long")


_add("measure_out_vs_rpq", _out_and_rpqs, query("timeline", f"SELECT 'OUT' AS relation, (SELECT count(*) FROM ({conjunction(['X', 'Y', 'U'], _four_atoms)})) AS n UNION ALL SELECT 'r1', (SELECT count(*) FROM r1) UNION ALL SELECT 'r2', (SELECT count(*) FROM er) UNION ALL SELECT 'r3', (SELECT count(*) FROM si) UNION ALL SELECT 'r4', (SELECT count(*) FROM cl)", *_four))


def _advantage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest expression's rows over the result's, for three queries: where materialising first is wasteful."""
    rows = []
    for name in ("four_atoms", "dangling", "nine_atoms"):
        g, e = _stored(spark, sf_dir, workloads.TEXTS[name][0])
        q = workloads.workload(name)
        largest = max(reach.pairs_capped(g, x, how=e).count() for x in dict.fromkeys(a.expr for a in q.atoms))
        out = ev.evaluate(q, g, how=e).count()
        rows.append((name, largest, out, round(largest / out, 3) if out else None))
    return spark.createDataFrame(rows, "name string, largest long, out long, ratio double")


_add("measure_advantage", _advantage, query(
    "timeline", "SELECT name, largest, out, round(largest / out, 3) AS ratio FROM (SELECT 'four_atoms' AS name, (SELECT count(*) FROM r1x) AS largest, (SELECT count(*) FROM o4) AS out UNION ALL SELECT 'dangling', (SELECT count(*) FROM c), (SELECT count(*) FROM od) UNION ALL SELECT 'nine_atoms', (SELECT count(*) FROM (SELECT DISTINCT c.x, er.y FROM c JOIN er ON c.y = er.x)), (SELECT count(*) FROM lt JOIN rt ON lt.a = rt.a))",
    *_nine, ("r1x", then("c", "pu")), ("ss", then("si", "si")), ("o4", conjunction(["X", "Y", "U"], [("r1x", "X", "Y"), ("er", "Y", "Z"), ("si", "Z", "W"), ("cl", "X", "U")])), ("od", conjunction(["X", "Y", "U"], [("pu", "X", "Y"), ("c", "Y", "U"), ("ss", "U", "W")])),
))


def _calibration(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the second atom's relation, with and without its children's messages, against the result's projection."""
    g, e = _stored(spark, sf_dir, "timeline")
    q, rows = workloads.workload("dangling"), []
    for name, on in (("calibrated", True), ("literal", False)):
        kept = []
        result = ev.eval_free_connex(q, g, how=e, child_filters=on, keep=kept)
        rows.append((name, kept[0][1].relations[q.atoms[1]].count()))
    rows.append(("projection", ev.calibrated(result, q.atoms[1]).count()))
    return spark.createDataFrame(rows, "relation string, n long")


_add("measure_calibrated", _calibration, query(
    "timeline",
    "SELECT 'projection' AS relation, (SELECT count(*) FROM r2 WHERE y IN (SELECT x FROM ss)) AS n UNION ALL SELECT 'calibrated', (SELECT count(*) FROM r2 WHERE y IN (SELECT x FROM ss)) UNION ALL SELECT 'literal', (SELECT count(*) FROM r2)",
    _all, ("p", edge("purchase")), ("s", edge("signup")), ("ss", then("s", "s")), ("r1", "SELECT p.x, p.y FROM p WHERE p.y IN (SELECT c.x FROM c JOIN ss ON c.y = ss.x)"), ("r2", "SELECT c.x, c.y FROM c WHERE c.x IN (SELECT y FROM r1)"),
))


def _bag_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of each bag's result before and after its promoted columns are dropped, and of the whole."""
    g, e = _stored(spark, sf_dir, "timeline")
    q, rows = workloads.workload("nine_atoms"), []
    for head in ev.bag_heads(q):
        own = q.with_head(head)
        c = ev.contract(own, g, how=e)
        before = e.scratch.table(ev.eval_free_connex(ev.promote(c.query, own), c.graph, filters=c.filters, how=e))
        rows += [("".join(sorted(head)) + " promoted", before.count()), ("".join(sorted(head)), before.select(*head).distinct().count())]
    rows.append(("OUT", ev.evaluate(q, g, how=e).count()))
    return spark.createDataFrame(rows, "relation string, n long")


_add("measure_bag_chain", _bag_chain, query(
    "timeline",
    "SELECT 'ACE promoted' AS relation, (SELECT count(*) FROM (SELECT DISTINCT r1.x AS a, r1.y AS b, vc.y AS c, be.e FROM r1 JOIN vc ON r1.y = vc.x JOIN be ON r1.y = be.b WHERE r1.x IN (SELECT a FROM rt))) AS n "
    "UNION ALL SELECT 'ACE', (SELECT count(*) FROM lt WHERE a IN (SELECT a FROM rt)) "
    "UNION ALL SELECT 'AGH promoted', (SELECT count(*) FROM (SELECT DISTINCT r5.x AS a, r5.y AS f, es.y AS g, vp.y AS h FROM r5 JOIN ok ON r5.y = ok.f JOIN es ON r5.y = es.x JOIN vp ON r5.y = vp.x WHERE r5.x IN (SELECT a FROM lt))) "
    "UNION ALL SELECT 'AGH', (SELECT count(*) FROM rt WHERE a IN (SELECT a FROM lt)) UNION ALL SELECT 'OUT', (SELECT count(*) FROM lt JOIN rt ON lt.a = rt.a)",
    *_nine,
))


def _bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes and analytic bounds of the four-atom query."""
    g, e = _stored(spark, sf_dir, "timeline")
    q, kept = workloads.workload("four_atoms"), []
    out = ev.eval_free_connex(q, g, how=e, keep=kept).count()
    out_c = max(df.count() for _, m in kept for df in m.relations.values())
    size = g.stats()
    b = ev.cost_bounds(q, size["vertices"], size["edges"], out, out_c)
    return spark.createDataFrame([(k, float(v)) for k, v in {**size, "out": out, "out_c": out_c, **b}.items()], "measure string, value double")


_add("measure_bounds", _bounds, query(
    "timeline",
    "SELECT unnest(['vertices', 'edges', 'out', 'out_c', 'ctw', 'contraction', 'free_connex', 'width_zero', 'driver']) AS measure, unnest([v, e, o, oc, 0.0, e, e + e * sqrt(oc) + o, e + e * sqrt(o) + o, e + e * sqrt(o) + o]) AS value FROM ("
    f"SELECT (SELECT count(*) FROM n)::DOUBLE AS v, (SELECT count(*) FROM g)::DOUBLE AS e, (SELECT count(*) FROM res)::DOUBLE AS o, greatest((SELECT count(*) FROM (SELECT DISTINCT X, Y FROM res)), (SELECT count(DISTINCT Y) FROM res), (SELECT count(*) FROM (SELECT DISTINCT X, U FROM res)))::DOUBLE AS oc)",
    *_four, ("res", conjunction(["X", "Y", "U"], _four_atoms)),
))


def _work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the capped search keeps to its bounds: cap, heavy sources and steps walked, of each graph."""
    rows = []
    for name, g in (("purchases", _stored(spark, sf_dir, "hop")[0]), ("fan", builders.fan_in_out(spark, 60, 60)), ("comb", builders.comb(spark, 8, 5))):
        e = ev.new_evaluation(g, mode="rounds", cap=2)
        text = "purchase*" if name == "purchases" else "a+"
        out, edges = reach.pairs_capped(g, regex.parse_path(text), how=e).count(), g.edges.count()
        tried = [r for r in e.log if r["stage"] == "capped"]
        last, transitions = tried[-1], len(regex.to_automaton(regex.parse_path(text)).transitions)
        rows.append((name, last["cap"] <= max(2, 2 * out**0.5), last["heavy"] <= last["cap"], sum(r["edges_touched"] for r in tried) <= 4 * transitions * edges * (last["cap"] + 1)))
    return spark.createDataFrame(rows, "graph string, cap_within boolean, heavy_within boolean, steps_within boolean")


_add("measure_work", _work, "SELECT * FROM (VALUES ('purchases', true, true, true), ('fan', true, true, true), ('comb', true, true, true)) v(graph, cap_within, heavy_within, steps_within)")


def _costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Time, shuffle and spill of the four-atom query by each method."""
    g, e = _stored(spark, sf_dir, "timeline")
    q = workloads.workload("four_atoms")
    return measure.compared(spark, {
        "parts": lambda: ev.evaluate(q, g, how=e), "free_connex": lambda: ev.eval_free_connex(q, g, how=e), "literal": lambda: ev.eval_free_connex(q, g, child_filters=False, how=e),
        "materialise": lambda: ev.base_materialise(q, g, e), "hypertree": lambda: ev.base_hypertree(q, g, e),
    })


_add("measure_costs", _costs)


# ---- around the methods


def _pairs_by_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(region, nation, label): customers and suppliers with the nation and region they are in."""
    g, e = _stored(spark, sf_dir, "supply")
    who = ev.evaluate(parse_query("W, N, R <- [c_in|s_in](W, N), [part_of](N, R)"), g, how=e)
    return who.select(F.col("R").alias("region"), F.col("N").alias("nation"), F.substring("W", 1, 1).alias("kind"), "W")


_who = [("ci", edge("c_in", "s_in")), ("po", edge("part_of")), ("who", "SELECT DISTINCT po.y AS region, ci.y AS nation, substr(ci.x, 1, 1) AS kind, ci.x AS w FROM ci JOIN po ON ci.y = po.x")]
_add("result_rollup_region", lambda s, d: surface.result_rollup(_pairs_by_region(s, d), ["region", "nation"], F.count(F.lit(1)).alias("n")), query("supply", "SELECT region, nation, count(*) AS n FROM who GROUP BY ROLLUP (region, nation)", *_who))
_add("result_cube", lambda s, d: surface.result_cube(_pairs_by_region(s, d), ["region", "kind"], F.count(F.lit(1)).alias("n")), query("supply", "SELECT region, kind, count(*) AS n FROM who GROUP BY CUBE (region, kind)", *_who))
_add("result_grouping_sets", lambda s, d: surface.result_grouping_sets(_pairs_by_region(s, d), [["region"], ["kind"]], "count(*)", "n"), query("supply", "SELECT region, kind, count(*) AS n FROM who GROUP BY GROUPING SETS ((region), (kind))", *_who))
_add("result_group", lambda s, d: surface.group_result(_pairs_by_region(s, d), ["region"], n="count(*)", nations="count(distinct nation)", least="min(W)", most="max(W)"), query("supply", "SELECT region, count(*) AS n, count(DISTINCT nation) AS nations, min(w) AS least, max(w) AS most FROM who GROUP BY region", *_who))
_add("result_topk", lambda s, d: surface.top_k(surface.group_result(_pairs_by_region(s, d), ["nation"], n="count(*)"), [F.desc("n"), "nation"], 5), query("supply", "SELECT nation, count(*) AS n FROM who GROUP BY nation ORDER BY n DESC, nation LIMIT 5", *_who))
_add("result_window_rank", lambda s, d: surface.rank_result(surface.group_result(_pairs_by_region(s, d), ["region", "nation"], n="count(*)"), ["region"], [F.desc("n"), "nation"]), query(
    "supply", "SELECT region, nation, n, row_number() OVER w AS row_number, rank() OVER w AS rank, dense_rank() OVER w AS dense_rank, ntile(4) OVER w AS ntile FROM (SELECT region, nation, count(*) AS n FROM who GROUP BY region, nation) WINDOW w AS (PARTITION BY region ORDER BY n DESC, nation)", *_who,
))
_add("edges_range_join", lambda s, d: builders.edges_range_join(read(s, d, "events"), ["user_id"], "ts", "event_id", 86_400, "within_a_day").edges, "SELECT DISTINCT a.event_id AS src, 'within_a_day' AS label, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND epoch_us(b.ts) > epoch_us(a.ts) AND epoch_us(b.ts) - epoch_us(a.ts) <= 86400000000")
_add("edges_asof", lambda s, d: builders.edges_asof(read(s, d, "events").where("event_type = 'purchase'"), read(s, d, "events").where("event_type = 'click'"), ["user_id"], "ts", "ts", "event_id", "event_id", "last_click", "event_id").edges, "SELECT src, label, dst FROM (SELECT a.event_id AS src, 'last_click' AS label, b.event_id AS dst, row_number() OVER (PARTITION BY a.event_id ORDER BY b.ts DESC, b.event_id DESC) AS r FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts <= a.ts WHERE a.event_type = 'purchase' AND b.event_type = 'click') WHERE r = 1")
_add("edges_interval", lambda s, d: builders.edges_interval(read(s, d, "events").where("event_type = 'view'"), read(s, d, "events").where("event_type = 'purchase'"), ["user_id"], "ts", "event_id", "ts", "event_id", 43_200, "bought_after_view").edges, "SELECT DISTINCT a.event_id AS src, 'bought_after_view' AS label, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND epoch_us(b.ts) >= epoch_us(a.ts) AND epoch_us(b.ts) < epoch_us(a.ts) + 43200000000 WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
_add("session_edges", lambda s, d: builders.session_edges(read(s, d, "events"), ["user_id"], "ts", "event_id", "event_id", "12 hours").edges, "SELECT src, label, dst FROM (SELECT lag(event_id) OVER w AS src, 'same_session' AS label, event_id AS dst, epoch_us(ts) - lag(epoch_us(ts)) OVER w AS gap FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE gap < 43200000000")


def _set(op: Callable) -> Run:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, "timeline")
        a, b = (reach.pairs_capped(g, regex.parse_path(t), how=e) for t in ("(view|click)*", "(click|error)*"))
        return op(a, b)

    return run


for _n, _op, _word in (("union", surface.union_results, "UNION"), ("intersect", surface.intersect_results, "INTERSECT"), ("except", surface.except_results, "EXCEPT")):
    _add(f"set_{_n}", _set(_op), query("timeline", f"SELECT x, y FROM a {_word} SELECT x, y FROM b", closure("a", "view", "click"), closure("b", "click", "error")))
_add("json_props", lambda s, d: read(s, d, "events").groupBy(builders.item(F.col("props")).alias("k")).agg(F.count(F.lit(1)).alias("n")), "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
_add("href_explode", lambda s, d: read(s, d, "pages").select(F.explode(builders.hrefs(F.col("html"))).alias("href")).groupBy("href").agg(F.count(F.lit(1)).alias("n")), """SELECT href, count(*) AS n FROM (SELECT unnest(regexp_extract_all(html, '<a[^>]*href="([^"]*)"', 1)) AS href FROM pages) GROUP BY href""")


def _text(text: str, graph: str) -> Run:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g, e = _stored(spark, sf_dir, graph)
        return surface.run(spark, text, g, e)

    return run


_add("constant_endpoint", _text("O, P <- [placed](O0, O), [contains_R](O, P), [c_in](O0, 'N3')", "supply"), query("supply", "SELECT DISTINCT pl.y AS O, cr.y AS P FROM pl JOIN cr ON pl.y = cr.x JOIN ci ON ci.x = pl.x WHERE ci.y = 'N3'", *_five))
_add("text_query", _text("X, Y <- [(user|assistant)+](X, Y), [assistant](Y, Z)", "talk"), query("talk", "SELECT DISTINCT c.x AS X, c.y AS Y FROM c JOIN e1 ON c.y = e1.x WHERE c.x <> c.y", closure("c"), ("e1", edge("assistant"))))
_add("web_colinks", _text("X, Y <- [links/^links](X, Y)", "web"), query("web", "SELECT DISTINCT a.x AS X, b.y AS Y FROM a JOIN b ON a.y = b.x", ("a", edge("links")), ("b", edge("links", back=True))))
_add("web_star", _text("H, Y <- [links](X, Y), [on_host](X, H)", "web"), query("web", "SELECT DISTINCT h.y AS H, l.y AS Y FROM l JOIN h ON l.x = h.x", ("l", edge("links")), ("h", edge("on_host"))))
_add("docs_copies", _text("X, Y <- [has_text/^has_text](X, Y), [rated](X, Q), [in_lang](Y, 'l:en')", "docs"), query("docs", "SELECT DISTINCT a.x AS X, b.x AS Y FROM t a JOIN t b ON a.y = b.y JOIN r ON r.x = a.x JOIN l ON l.x = b.x WHERE l.y = 'l:en'", ("t", edge("has_text")), ("r", edge("rated")), ("l", edge("in_lang"))))
_add("docs_quotes", _text("D, B, S <- [quotes](D, B), [from_source](D, S)", "docs"), query("docs", "SELECT DISTINCT q.x AS D, q.y AS B, s.y AS S FROM q JOIN s ON q.x = s.x", ("q", edge("quotes")), ("s", edge("from_source"))))
_add("talk_any", _rpq("talk", ".*"), _pairs("talk", "SELECT * FROM c", closure("c")))
_add("near_same", _rpq("near", "same+"), _pairs("near", then("s", "c"), ("s", edge("same")), closure("c", "same")))
_add("near_mixed", _rpq("near", "same*/diff"), _pairs("near", then("c", "d"), closure("c", "same"), ("d", edge("diff"))))
_add("cosine_edges", builders.cosine_edges, query("near", "SELECT src, g.label, dst, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS cosine FROM g JOIN embeddings a ON a.vec_id = src JOIN embeddings b ON b.vec_id = dst"))
_add("cosine_edges_vectorised", lambda s, d: builders.cosine_edges(s, d, by=vectorised.cosine), ORACLES["cosine_edges"])
_add("degree_deviation", lambda s, d: builders.supply(s, d).edges.groupBy("label", "src").count().groupBy("label").agg(F.round(vectorised.deviation("count"), 6).alias("deviation")), query("supply", "SELECT label, round(stddev_pop(n), 6) AS deviation FROM (SELECT label, src, count(*) AS n FROM g GROUP BY label, src) GROUP BY label"))
_add("running_degree", lambda s, d: surface.running_degree(builders.timeline(s, d).edges, "part", ["dst"], "dst"), query(
    "timeline", "SELECT part, dst, so_far, first, second, len(list_filter(near, lambda x: x = label)) AS recent FROM (SELECT user_id AS part, dst, label, count(*) OVER (PARTITION BY user_id ORDER BY dst) AS so_far, first_value(dst) OVER w AS first, nth_value(dst, 2) OVER w AS second, list(label) OVER (PARTITION BY user_id ORDER BY dst ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS near FROM g JOIN events ON event_id = dst WINDOW w AS (PARTITION BY user_id ORDER BY dst ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING))",
))
_add("udtf_pairs", surface.udtf_pairs, _pairs("talk", then("a", "c"), ("a", edge("user")), closure("c", "assistant", "user")))
_add("explain_cost", lambda s, d: surface.explain_cost(workloads.workload("nine_atoms"), *_stored(s, d, "timeline")))
_add("stream_timeline", feed.replayed_timeline, query("timeline", "SELECT src, label, dst FROM g"))
_add("stream_windows", feed.windowed_counts, "SELECT time_bucket(INTERVAL '1 day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")

