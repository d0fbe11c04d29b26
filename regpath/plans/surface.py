"""What stands around the methods: query text, reports, and operations on results."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from regpath.functions.regex import parse_path, to_automaton
from regpath.operators.reach import Evaluation
from regpath.plans import evaluate as ev
from regpath.plans import structure as st
from regpath.plans.query import PathQuery, parse_query
from regpath.sources.graph import LabeledGraph


def run(spark: SparkSession, text: str, g: LabeledGraph, how: Evaluation | None = None, **options) -> DataFrame:
    """Evaluates `X, Y <- [expression](X, Z), ...` over a graph."""
    return ev.evaluate(parse_query(text), g, how=how, **options)


def explain_query(q: PathQuery, g: LabeledGraph | None = None) -> str:
    """The analysis of a query: pieces, decomposition, and for each bag what contraction takes out and what stays."""
    st.check_acyclic(q)
    lines = [str(q), f"free-connex: {st.is_free_connex(q)}; contraction width {st.ctw(q)}; free-connex hypertree width {st.fhtw(q)}"]
    lines += [f"piece {sorted(p)} with free {sorted(f)}" for p, f in st.pieces(q)]
    for head in ev.bag_heads(q):
        order, left = st.elimination_order(q.with_head(head))
        lines.append(f"bag {list(head)}: takes out {order}; promotes {[v for v in left if v not in head]}")
    if st.is_free_connex(q):
        for atoms in st.trees(q):
            tree = st.free_top_join_tree(q, atoms)
            lines += [f"{a} under {tree.parent[a]} by {tree.via[a]}" if a in tree.parent else f"{a} is a root" for a in tree.order]
    if g is not None:
        size = g.stats()
        lines.append(f"{size['vertices']} vertices, {size['edges']} edges; bounds for a result as large as the edges: {ev.cost_bounds(q, size['vertices'], size['edges'], size['edges'], size['edges'])}")
    return "\n".join(lines)


def explain_cost(q: PathQuery, g: LabeledGraph, how: Evaluation) -> DataFrame:
    """(stage, relation, n): sizes that one evaluation met, bag by bag, and the whole."""
    rows = []
    for head in ev.bag_heads(q):
        own, name = q.with_head(head), "".join(head)
        c = ev.contract(own, g, how=how)
        rows += [("contract", f"{name}: filter of {v}", fs[0].count()) for v, fs in c.filters.items()]
        kept: list = []
        found = ev.eval_free_connex(ev.promote(c.query, own), c.graph, filters=c.filters, how=how, keep=kept)
        for _, m in kept:
            for stage, made in (("up", m.up), ("down", m.down), ("relation", m.relations)):
                rows += [(stage, f"{name}: {a}", df.count()) for a, df in made.items() if isinstance(df, DataFrame)]
        rows.append(("bag", name, found.count()))
    rows.append(("result", str(q), ev.evaluate(q, g, how=how).count()))
    return g.edges.sparkSession.createDataFrame(rows, "stage string, relation string, n long")


# ---- operations on results


def group_result(df: DataFrame, keys: list[str], **aggs: str) -> DataFrame:
    """Aggregates given as SQL, by their names."""
    return df.groupBy(*keys).agg(*[F.expr(e).alias(n) for n, e in aggs.items()])


def result_rollup(df: DataFrame, columns: list[str], *aggs: Column) -> DataFrame:
    return df.rollup(*columns).agg(*aggs)


def result_cube(df: DataFrame, columns: list[str], *aggs: Column) -> DataFrame:
    return df.cube(*columns).agg(*aggs)


def result_grouping_sets(df: DataFrame, sets: list[list[str]], agg: str, name: str) -> DataFrame:
    columns = list(dict.fromkeys(c for s in sets for c in s))
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *columns).agg(F.expr(agg).alias(name))


def rank_result(df: DataFrame, partition: list[str], order: list) -> DataFrame:
    w = Window.partitionBy(*partition).orderBy(*order)
    return df.select("*", F.row_number().over(w).alias("row_number"), F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense_rank"), F.ntile(4).over(w).alias("ntile"))


def top_k(df: DataFrame, order: list, k: int) -> DataFrame:
    return df.orderBy(*order).limit(k)


def union_results(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).distinct()


def intersect_results(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.intersect(b.select(*a.columns))


def except_results(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.subtract(b.select(*a.columns))


def write_result(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", partition_by: list[str] | None = None) -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


# ---- a table function for SQL, over graphs with closed parts


class PathPairs:
    """eval: rows of one part (src, label, dst); terminate: pairs that an expression links within it."""

    def __init__(self) -> None:
        self.edges, self.text = [], ""

    def eval(self, row, text: str):
        self.edges.append((row["src"], row["label"], row["dst"]))
        self.text = text

    def terminate(self):
        if not self.edges:
            return
        a = to_automaton(parse_path(self.text))
        ahead: dict = {}
        for u, label, v in self.edges:
            for q, s, p in a.transitions:
                if (label in s.labels) != s.negated:
                    ahead.setdefault((v, q) if s.inverse else (u, q), []).append((u, p) if s.inverse else (v, p))
        for s in sorted({x for u, _, v in self.edges for x in (u, v)}):
            seen, todo = {(s, 0)}, [(s, 0)]
            while todo:
                for n in ahead.get(todo.pop(), ()):
                    if n not in seen:
                        seen.add(n)
                        todo.append(n)
            for v in sorted({v for v, q in seen if q in a.finals}):
                yield s, v


def register_udtf(spark: SparkSession) -> None:
    """path_pairs(TABLE(edges) PARTITION BY (part), 'expression') for edges with long ends."""
    spark.udtf.register("path_pairs", F.udtf(PathPairs, returnType="x bigint, y bigint"))


def udtf_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of turns through the table function, one conversation at a time."""
    from regpath.sources.builders import talk

    register_udtf(spark)
    talk(spark, sf_dir).edges.createOrReplaceTempView("regpath_talk_edges")
    return spark.sql("SELECT x, y FROM path_pairs(TABLE(regpath_talk_edges) PARTITION BY (part), 'user/(user|assistant)*')")


def running_degree(edges: DataFrame, key: str, order: list[str], vertex: str) -> DataFrame:
    """(key, vertex, so_far, first, second, recent): edges of a key up to each one, the key's first and second target, and edges among the last three that share its label."""
    w = Window.partitionBy(key).orderBy(*order)
    upto, whole, recent = w.rowsBetween(Window.unboundedPreceding, 0), w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing), w.rowsBetween(-2, 0)
    same = F.size(F.filter(F.collect_list("label").over(recent), lambda x: x == F.col("label")))
    return edges.select(key, vertex, F.count(F.lit(1)).over(upto).alias("so_far"), F.first(vertex).over(whole).alias("first"), F.nth_value(vertex, 2).over(whole).alias("second"), same.alias("recent"))
