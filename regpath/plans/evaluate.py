"""Evaluation of acyclic queries: free-connex evaluation, contraction, and the driver over decompositions."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from regpath.functions.regex import Guard, compose, invert, letters
from regpath.operators.joins import acyclic_join, natural
from regpath.operators.parts import evaluate_parts
from regpath.operators.reach import Evaluation, holds, pairs_capped, reach_unary
from regpath.operators.scratch import Scratch
from regpath.plans.query import Atom, PathQuery
from regpath.plans.structure import Decomposition, canonical_decomposition, check_acyclic, free_top_join_tree, is_free_connex, trees
from regpath.sources.graph import LabeledGraph

Filters = dict[str, list[DataFrame]]


def new_evaluation(g: LabeledGraph, **how) -> Evaluation:
    return Evaluation(Scratch(g.edges.sparkSession, "query"), **how)


def _constants(q: PathQuery, g: LabeledGraph) -> Filters:
    schema = T.StructType([T.StructField("v", g.vertex_type)])
    return {v: [g.edges.sparkSession.createDataFrame([(c,)], schema)] for v, c in q.constants.items()}


def _result(q: PathQuery, g: LabeledGraph, answer: bool) -> DataFrame:
    """The result of a query without free variables, or an empty one of a query with some."""
    if not q.head:
        return g.edges.sparkSession.createDataFrame([(answer,)], "answer boolean")
    return g.edges.where(F.lit(False)).select(*[F.col("src").alias(v) for v in q.head])


# ---- free-connex evaluation


@dataclass
class Messages:
    """What the passes over one join tree have made: upward messages, and relations of atoms with a free variable."""

    up: dict[Atom, DataFrame | bool] = field(default_factory=dict)
    down: dict[Atom, DataFrame] = field(default_factory=dict)
    relations: dict[Atom, DataFrame] = field(default_factory=dict)


def _unary(atom: Atom, keep: str, g: LabeledGraph, filters: Filters, how: Evaluation) -> DataFrame:
    x_in, y_in = filters.get(atom.x, []), filters.get(atom.y, [])
    return reach_unary(g, atom.expr, "x" if keep == atom.x else "y", x_in, y_in, True, how)


def _relation(atom: Atom, free: frozenset[str], g: LabeledGraph, filters: Filters, how: Evaluation) -> DataFrame | bool:
    """The atom under the filters, on its free ends: pairs, vertices, or a truth value."""
    ends = [v for v in (atom.x, atom.y) if v in free]
    if len(ends) == 2:
        return pairs_capped(g, atom.expr, filters.get(atom.x, []), filters.get(atom.y, []), True, how).select(F.col("x").alias(atom.x), F.col("y").alias(atom.y))
    if len(ends) == 1:
        return _unary(atom, ends[0], g, filters, how).select(F.col("v").alias(ends[0]))
    return holds(_unary(atom, atom.x, g, filters, how))


def _with(filters: Filters, more: list[tuple[str, DataFrame]]) -> Filters:
    out = dict(filters)
    for v, df in more:
        out[v] = [*out.get(v, []), df]
    return out


def _together(jobs: list[Callable]) -> list:
    """Results of jobs that do not need each other; their Spark jobs run side by side."""
    if len(jobs) < 2:
        return [j() for j in jobs]
    with ThreadPoolExecutor(len(jobs)) as pool:
        return [f.result() for f in [pool.submit(j) for j in jobs]]


def _levels(tree) -> list[list[Atom]]:
    """Atoms by their distance from the root."""
    depth: dict[Atom, int] = {}
    for a in tree.order:
        depth[a] = depth[tree.parent[a]] + 1 if a in tree.parent else 0
    return [[a for a in tree.order if depth[a] == d] for d in range(max(depth.values()) + 1)]


def upward(q: PathQuery, tree, g: LabeledGraph, filters: Filters, how: Evaluation) -> Messages:
    """From the leaves: each atom tells its parent which values of their common variable it can go on from."""
    made = Messages()

    def message(a: Atom) -> DataFrame | bool:
        under = _with(filters, [(tree.via[c], made.up[c]) for c in tree.children(a)])
        if a is not tree.root:
            how.note(stage="up", relation=str(a), var=tree.via[a])
            return how.scratch.table(_unary(a, tree.via[a], g, under, how))
        root = _relation(a, q.free, g, under, how)
        return how.scratch.table(root) if isinstance(root, DataFrame) and len(tree.order) > 1 else root

    for level in reversed(_levels(tree)[1:]):
        made.up.update(zip(level, _together([lambda a=a: message(a) for a in level]), strict=True))
    made.relations[tree.root] = message(tree.root)
    return made


def downward(q: PathQuery, tree, g: LabeledGraph, made: Messages, filters: Filters, how: Evaluation, child_filters: bool = True) -> Messages:
    """From the root: each atom with a free variable under its parent's relation; and its children's messages, unless `child_filters` is off."""

    def relation(a: Atom) -> DataFrame | bool:
        own = [(tree.via[a], made.down[a])]
        if child_filters:
            own += [(tree.via[c], made.up[c]) for c in tree.children(a)]
        how.note(stage="down", relation=str(a))
        return how.scratch.table(_relation(a, q.free, g, _with(filters, own), how))

    for level in _levels(tree)[1:]:
        own = []
        for a in level:
            parent = made.relations.get(tree.parent[a])
            if a.ends & q.free and isinstance(parent, DataFrame) and tree.via[a] in parent.columns:
                made.down[a] = parent.select(F.col(tree.via[a]).alias("v")).distinct()
                own.append(a)
        made.relations.update(zip(own, _together([lambda a=a: relation(a) for a in own]), strict=True))
    return made


def eval_free_connex(q: PathQuery, g: LabeledGraph, root: Atom | None = None, child_filters: bool = True, filters: Filters | None = None, how: Evaluation | None = None, keep: list | None = None) -> DataFrame:
    """Result of a free-connex query: calibrated relations of its atoms, then their join.

    Filters restrict variables.  Trees without a free variable are truth values;
    trees that share no variable multiply, once each is known to have a row.
    keep: gets the messages of each tree.
    """
    if not is_free_connex(q):
        raise ValueError("the free variables are not connected: contract or decompose the query")
    how = how or new_evaluation(g)
    filters = _merge(filters or {}, _constants(q, g))
    relations: list[DataFrame] = []
    parts = sorted(trees(q), key=lambda t: bool({v for a in t for v in a.ends} & q.free))
    for atoms in parts:
        tree = free_top_join_tree(q, atoms, root if root in atoms else None)
        made = upward(q, tree, g, filters, how)
        if keep is not None:
            keep.append((tree, made))
        if made.relations[tree.root] is False:
            return _result(q, g, False)
        if made.relations[tree.root] is True:
            continue
        if len(parts) > 1 and not holds(made.relations[tree.root]):
            return _result(q, g, False)
        downward(q, tree, g, made, filters, how, child_filters)
        relations += [made.relations[a] for a in tree.order if a in made.relations]
    if not relations:
        return _result(q, g, True)
    if len(relations) == 1 and set(relations[0].columns) == set(q.head):
        return relations[0].select(*q.head)  # relations of atoms have no row twice
    return acyclic_join(relations, list(q.head), reduced=True)


def _merge(a: Filters, b: Filters) -> Filters:
    return {v: [*a.get(v, []), *b.get(v, [])] for v in {*a, *b}}


# ---- contraction


@dataclass(frozen=True)
class Contracted:
    """A query over fewer variables with the same result, the filters that go with it, and what is left of vanished parts.

    lone: free variables without an atom, with their filters (None: all vertices).
    truths: filters of vanished parts without a free variable; each must have a row.
    """

    query: PathQuery
    graph: LabeledGraph
    filters: Filters
    lone: dict[str, DataFrame]
    truths: tuple[DataFrame, ...]
    steps: tuple[str, ...]


def contract(q: PathQuery, g: LabeledGraph, order=None, skip_trivial_guards: bool = True, how: Evaluation | None = None, memo: dict | None = None) -> Contracted:
    """Takes out bound variables of one atom, which becomes a filter of its other end, or of two, which become one.

    A variable's filter is final when it is taken out of the middle of two atoms, so it
    is named as a guard there and then; later filters may walk through it.
    """
    how = how or new_evaluation(g)
    memo = {} if memo is None else memo
    filters: dict[str, DataFrame | None] = {}
    for v, fs in _constants(q, g).items():
        filters[v] = fs[0]
    atoms, lone, truths, steps = list(q.atoms), {}, [], []
    names: dict[str, str] = {v: f"const:{c}" for v, c in q.constants.items()}  # what each filter stands for, to know equal ones again

    def degree(v: str) -> int:
        return sum(v in a.ends for a in atoms)

    def ready() -> list[str]:
        return [v for v in dict.fromkeys(u for a in atoms for u in (a.x, a.y)) if v not in q.free and degree(v) <= 2]

    while todo := ready():
        if order is None or order in ("leaves_first", "paths_first"):
            v = min(todo, key=lambda u: degree(u) != (2 if order == "paths_first" else 1))
        else:
            v = min(todo, key=lambda u: list(order).index(u) if u in order else len(list(order)))
        mine = [a for a in atoms if v in a.ends]
        at = min(atoms.index(a) for a in mine)
        if len(mine) == 1:
            a, n = mine[0], mine[0].other(v)
            key = (str(a.expr if a.x == n else invert(a.expr)), names.get(n), names.get(v))
            if key not in memo:
                under = {u: [filters[u]] for u in (v, n) if filters.get(u) is not None}
                memo[key] = how.scratch.table(_unary(a, n, g, under, how))
            filters[n], names[n] = memo[key], str(key)
            atoms.remove(a)
            steps.append(f"{v}: filter of {n}")
            if not any(n in b.ends for b in atoms):
                if n in q.free:
                    lone[n] = filters[n]
                else:
                    truths.append(filters[n])
        else:
            first, second = mine
            e1 = first.expr if first.y == v else invert(first.expr)
            e2 = second.expr if second.x == v else invert(second.expr)
            guard = None
            if filters.get(v) is not None or not skip_trivial_guards:
                guard = v + "" if v not in g.guards else f"{v}#{len(g.guards)}"
                g = g.with_guard(guard, filters[v] if filters.get(v) is not None else how.scratch.table(g.vertices().select("v")))
            joined = Atom(compose(e1, guard, e2), first.other(v), second.other(v))
            atoms = [b for b in atoms if b not in mine]
            atoms.insert(at, joined)
            steps.append(f"{v}: {joined}")
    kept = tuple(v for v in q.head if v not in lone)
    left = {u for a in atoms for u in a.ends}
    out = PathQuery(kept, tuple(atoms))
    return Contracted(out, g, {v: [f] for v, f in filters.items() if f is not None and v in left}, lone, tuple(truths), tuple(steps))


# ---- the driver


def promote(q2: PathQuery, q: PathQuery) -> PathQuery:
    """The contracted query with all its bound variables free, behind those that are."""
    return q2.with_head([*q2.head, *(v for v in q2.vars if v not in q2.free)])


def _join_variables(q: PathQuery) -> list[str]:
    return [v for v in q.bound if len(q.at(v)) > 1]


def bag_heads(q: PathQuery, decomposition="auto") -> list[tuple[str, ...]]:
    """Heads of the bags' induced queries; those within another are left out, and so are bags without free variables if any has some."""
    if decomposition == "single":
        return [q.head]
    d = canonical_decomposition(q) if decomposition == "auto" else decomposition
    if isinstance(d, Decomposition) and decomposition != "auto":
        d.validate(q)
    heads = list(dict.fromkeys(q.induced(b).head for b in d.bags))
    return [h for h in heads if not any(set(h) < set(o) for o in heads)] or [()]


def evaluate(q: PathQuery, g: LabeledGraph, decomposition="auto", contract_first: bool = True, how: Evaluation | None = None, order=None, skip_trivial_guards: bool = True, child_filters: bool = True) -> DataFrame:
    """The result of an acyclic query: one column for each free variable, or one row `answer` without any.

    For each bag of a free-connex decomposition, the query is contracted, bound
    variables that are left are made free, the query is evaluated, and their columns
    are dropped; the bags' results are joined.  decomposition: 'auto' (least
    width), 'single' (one bag), or one of your own.  contract_first=False makes all bound join
    variables free instead.  Over a graph of closed parts all this is done within each part, in one job.
    """
    check_acyclic(q)
    how = how or new_evaluation(g)
    if isinstance(decomposition, Decomposition):
        decomposition.validate(q)
    if how.budget is not None:
        _within_budget(q, g, decomposition, how.budget)
    if how.mode == "auto" and g.parted and not g.guards and not g.closed and contract_first and child_filters and order is None and skip_trivial_guards and not _has_guards(q):
        return _by_parts(q, g, decomposition, how)
    memo: dict = {}
    # bags have one body: contracted one after the other, they find each other's filters
    made = []
    for head in bag_heads(q, decomposition):
        own = q.with_head(head)
        c = contract(own, g, order, skip_trivial_guards, how, memo) if contract_first else Contracted(own, g, _constants(q, g), {}, (), ())
        made.append((own, c))

    def result(own: PathQuery, c: Contracted) -> DataFrame | bool:
        found = _bag(own, c, how, contract_first, child_filters)
        return how.scratch.table(found) if isinstance(found, DataFrame) and len(made) > 1 else found

    results = _together([lambda m=m: result(*m) for m in made])
    if any(r is False for r in results):
        return _result(q, g, False)
    relations = [r for r in results if r is not True]
    if not relations:
        return _result(q, g, True)
    if len(relations) == 1:
        return relations[0].select(*q.head)
    return acyclic_join(relations, list(q.head), reduced=True)


def _has_guards(q: PathQuery) -> bool:
    return any(isinstance(x, Guard) for a in q.atoms for x in letters(a.expr))


def _by_parts(q: PathQuery, g: LabeledGraph, decomposition, how: Evaluation) -> DataFrame:
    """Each connected part of the query within each closed part of the graph; then their product."""
    out, parts = [], trees(q)
    for atoms in parts:
        used = {v for a in atoms for v in a.ends}
        own = PathQuery(tuple(v for v in q.head if v in used), tuple(atoms), {v: c for v, c in q.constants.items() if v in used})
        whole = decomposition if decomposition in ("auto", "single") else "auto"
        found = evaluate_parts(own, g, bag_heads(own, whole))
        how.note(stage="parts", relation=str(own))
        if not own.head:
            if not holds(found):
                return _result(q, g, False)
        else:
            out.append(how.scratch.table(found) if len(parts) > 1 else found)
    return reduce(natural, out).select(*q.head) if out else _result(q, g, True)


def _within_budget(q: PathQuery, g: LabeledGraph, decomposition, budget: float) -> None:
    """Raises if the driver's bound, for a result as large as the edges, is beyond the budget."""
    size = g.stats(approx=True)
    d = decomposition if isinstance(decomposition, Decomposition) else None
    if decomposition == "single":
        d = Decomposition((q.free, frozenset(q.vars)), ((0, 1),))
    bound = cost_bounds(q, size["vertices"], size["edges"], size["edges"], size["edges"], d)["driver"]
    if bound > budget:
        raise BudgetError(f"the bound {bound:.3g} is beyond the budget {budget:.3g}")


class BudgetError(RuntimeError):
    """The bound of a query is beyond the budget that was given."""


def _bag(own: PathQuery, c: Contracted, how: Evaluation, contracted: bool, child_filters: bool) -> DataFrame | bool:
    if not all(holds(t) for t in c.truths):
        return False
    parts = [f.select(F.col("v").alias(v)) for v, f in c.lone.items()]
    if c.query.atoms:
        q2 = promote(c.query, own) if contracted else own.with_head([*own.head, *_join_variables(own)])
        found = eval_free_connex(q2, c.graph, None, child_filters, c.filters, how)
        if not q2.head:
            if not found.first()["answer"]:
                return False
        else:
            how.note(stage="bag", head=list(own.head), promoted=[v for v in q2.head if v not in own.free])
            if not own.head:
                return holds(found)
            kept = [v for v in own.head if v in q2.free]
            if kept:
                parts.append(found.select(*kept) if set(kept) == set(found.columns) else found.select(*kept).distinct())
            elif not holds(found):
                return False
    if not parts:
        return not own.head
    return reduce(natural, parts).select(*own.head)


# ---- baselines


def base_materialise(q: PathQuery, g: LabeledGraph, how: Evaluation | None = None, output_sensitive: bool = False, limit: int = 64) -> DataFrame:
    """Every atom in full, then the classical join: semi-joins both ways, joins, projection.

    output_sensitive: bound join variables are projected away one by one, with
    their heavy values joined apart.
    """
    from regpath.operators.joins import heavy_light_join

    check_acyclic(q)
    how = how or new_evaluation(g)
    filters = _constants(q, g)
    full = [how.scratch.table(_relation(a, a.ends, g, {v: filters[v] for v in a.ends if v in filters}, how)) for a in q.atoms]
    if not q.head:
        return _result(q, g, holds(acyclic_join(full, list(q.atoms[0].ends))))
    if not output_sensitive:
        return acyclic_join(full, list(q.head))
    rows = list(full)
    for v in q.bound:
        mine = [r for r in rows if v in r.columns]
        rest = [r for r in rows if v not in r.columns]
        while len(mine) > 2:
            b = mine.pop()
            mine[0] = natural(mine[0], b)
        columns = sorted({c for r in mine for c in r.columns} - {v})
        made = heavy_light_join(mine[0], mine[1], v, columns, limit) if len(mine) == 2 else mine[0].select(*columns).distinct()
        rows = [*rest, how.scratch.table(made)] if columns else rest
        if not columns and not holds(mine[0]):
            return _result(q, g, False)
    if any(not holds(r) for r in rows):
        return _result(q, g, False)
    return reduce(natural, rows).select(*q.head).distinct()


def base_hypertree(q: PathQuery, g: LabeledGraph, how: Evaluation | None = None) -> DataFrame:
    """Full atoms joined bag by bag of the canonical decomposition, whatever the bags' sizes; then semi-joins and joins of the bags."""
    from regpath.plans.structure import pieces

    check_acyclic(q)
    how = how or new_evaluation(g)
    filters = _constants(q, g)
    bags = []
    for vars_, free in pieces(q):
        own = [a for a in q.atoms if a.ends <= vars_ and (a.ends - q.free or len(vars_) == 2)]
        joined = reduce(natural, [_relation(a, a.ends, g, {v: filters[v] for v in a.ends if v in filters}, how) for a in own])
        if free:
            bags.append(how.scratch.table(joined.select(*sorted(free)).distinct()))
        elif not holds(joined):
            return _result(q, g, False)
    return acyclic_join(bags, list(q.head)) if bags else _result(q, g, True)


def base_bruteforce(q: PathQuery, g: LabeledGraph, how: Evaluation | None = None) -> DataFrame:
    """All maps of the variables to vertices, tried one by one; for graphs of a few vertices."""
    check_acyclic(q)
    how = how or new_evaluation(g)
    v = how.scratch.table(g.vertices().select("v"))
    constants = _constants(q, g)
    maps = reduce(lambda a, b: a.crossJoin(b), [v.join(constants[x][0], "v", "left_semi").withColumnRenamed("v", x) if x in constants else v.withColumnRenamed("v", x) for x in q.vars])
    for a in q.atoms:
        maps = maps.join(_relation(a, a.ends, g, {}, how), [a.x, a.y], "left_semi")
    return maps.select(*q.head).distinct() if q.head else _result(q, g, holds(maps))


def calibrated(result: DataFrame, atom: Atom) -> DataFrame:
    """The result on an atom's free ends."""
    return result.select(*[v for v in (atom.x, atom.y) if v in result.columns]).distinct()


def cost_bounds(q: PathQuery, vertices: int, edges: int, out: int, out_c: int, decomposition: Decomposition | None = None) -> dict[str, float]:
    """The analytic bounds of the methods, up to constants, for given sizes."""
    from regpath.plans.structure import ctw_of

    w = ctw_of(q, decomposition or canonical_decomposition(q))
    return {
        "ctw": w, "contraction": float(edges), "free_connex": edges + edges * out_c**0.5 + out, "width_zero": edges + edges * out**0.5 + out,
        "driver": edges + edges * out**0.5 * vertices ** (w / 2) + out * float(vertices) ** w,
    }


