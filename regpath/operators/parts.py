"""Whole queries within closed parts of a graph.

Where no walk leaves a part, neither does any match of a connected query.  So
each part's edges go to one task once, which contracts the query and evaluates
it there with the same passes as over tables: filters first, then calibrated relations, then
their join.  A query costs one shuffle of the edges that its labels take.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from regpath.functions.regex import PathExpr, Step, compose, invert, letters, nullable, to_automaton
from regpath.plans.query import Atom, PathQuery
from regpath.plans.structure import free_top_join_tree
from regpath.sources.graph import LabeledGraph

automaton = lru_cache(maxsize=1_000)(to_automaton)
flipped = lru_cache(maxsize=1_000)(invert)


class Part:
    """The edges of one part, and walks over them."""

    def __init__(self, edges: list[tuple]) -> None:
        self.edges = edges
        self.guards: dict[str, set] = {}
        self._steps: dict[PathExpr, dict] = {}
        self._vertices: set | None = None

    @property
    def vertices(self) -> set:
        if self._vertices is None:
            self._vertices = {x for u, _, v in self.edges for x in (u, v)}
        return self._vertices

    def steps(self, e: PathExpr) -> dict:
        if e not in self._steps:
            ahead: dict = {}
            for q, x, p in automaton(e).transitions:
                if isinstance(x, Step):
                    for u, label, v in self.edges:
                        if (label in x.labels) != x.negated:
                            ahead.setdefault((v, q) if x.inverse else (u, q), []).append((u, p) if x.inverse else (v, p))
                else:
                    for u in self.guards[x.name]:
                        ahead.setdefault((u, q), []).append((u, p))
            self._steps[e] = ahead
        return self._steps[e]

    def ends(self, e: PathExpr, starts: set | None, within: set | None) -> set:
        """Vertices to which `e` leads from any of the starts."""
        ahead, finals = self.steps(e), automaton(e).finals
        first = {n for n in ahead if n[1] == 0 and (starts is None or n[0] in starts)}
        todo, seen, out = list(first), set(first), set()
        while todo:
            for n in ahead.get(todo.pop(), ()):
                if n[1] in finals:
                    out.add(n[0])
                if n not in seen:
                    seen.add(n)
                    todo.append(n)
        if nullable(e):
            out |= self.vertices if starts is None else starts & self.vertices
        return out if within is None else out & within

    def keep(self, e: PathExpr, keep_x: bool, xs: set | None, ys: set | None) -> set:
        return self.ends(flipped(e), ys, xs) if keep_x else self.ends(e, xs, ys)

    def pairs(self, e: PathExpr, xs: set | None, ys: set | None) -> set[tuple]:
        """Both ends: a search from each start that leads to an end, through vertices that do."""
        live = self.keep(e, True, xs, ys)
        return {(x, y) for x in live for y in self.ends(e, {x}, ys)}


def _meet(a: set | None, b: set | None) -> set | None:
    return b if a is None else a if b is None else a & b


def _contracted(part: Part, q: PathQuery, filters: dict[str, set | None]) -> tuple[list[Atom], dict[str, set | None], dict[str, set], bool]:
    """(atoms, filters, free variables left without an atom, whether all vanished parts hold)."""
    atoms, filters, lone = list(q.atoms), dict(filters), {}
    while True:
        degree: dict[str, int] = {}
        for a in atoms:
            for v in (a.x, a.y):
                degree[v] = degree.get(v, 0) + 1
        ready = [v for v in degree if v not in q.free and degree[v] <= 2]
        if not ready:
            return atoms, filters, lone, True
        v = min(ready, key=lambda u: degree[u])
        mine = [a for a in atoms if v in a.ends]
        at = atoms.index(mine[0])
        atoms = [a for a in atoms if v not in a.ends]
        if len(mine) == 1:
            a = mine[0]
            n = a.other(v)
            filters[n] = part.keep(a.expr, a.x == n, filters.get(a.x), filters.get(a.y))
            if not any(n in b.ends for b in atoms):
                if n in q.free:
                    lone[n] = filters[n]
                elif not filters[n]:
                    return atoms, filters, lone, False
        else:
            first, second = mine
            e1 = first.expr if first.y == v else flipped(first.expr)
            e2 = second.expr if second.x == v else flipped(second.expr)
            if filters.get(v) is not None:
                part.guards[v] = filters[v]
            atoms.insert(at, Atom(compose(e1, v if filters.get(v) is not None else None, e2), first.other(v), second.other(v)))


def _joined(parts: list[tuple[tuple[str, ...], set[tuple]]]) -> tuple[tuple[str, ...], set[tuple]]:
    names, rows = parts[0]
    for other, more in parts[1:]:
        common = [v for v in other if v in names]
        new = [i for i, v in enumerate(other) if v not in names]
        by: dict = {}
        for r in more:
            by.setdefault(tuple(r[other.index(v)] for v in common), []).append(tuple(r[i] for i in new))
        here = [names.index(v) for v in common]
        rows = {(*r, *t) for r in rows for t in by.get(tuple(r[i] for i in here), ())}
        names = (*names, *(other[i] for i in new))
    return names, rows


def _connex(part: Part, head: tuple[str, ...], atoms: list[Atom], filters: dict[str, set | None]) -> tuple[tuple[str, ...], set[tuple]]:
    """Calibrated relations of one connected free-connex query, joined."""
    q = PathQuery(head, tuple(atoms))
    tree = free_top_join_tree(q, atoms)
    up: dict[Atom, set] = {}

    def relation(a: Atom, more: list[tuple[str, set]]) -> tuple[tuple[str, ...], set[tuple]]:
        own = {v: filters.get(v) for v in a.ends}
        for v, s in more:
            own[v] = _meet(own[v], s)
        free = tuple(v for v in (a.x, a.y) if v in q.free)
        if len(free) == 2:
            return free, part.pairs(a.expr, own[a.x], own[a.y])
        kept = part.keep(a.expr, free != (a.y,), own[a.x], own[a.y])
        return free, {(v,) for v in kept} if free else ({()} if kept else set())

    for a in reversed(tree.order):
        below = [(tree.via[c], up[c]) for c in tree.children(a)]
        if a is tree.root:
            found = {a: relation(a, below)}
        else:
            own = {v: filters.get(v) for v in a.ends}
            for v, s in below:
                own[v] = _meet(own[v], s)
            up[a] = part.keep(a.expr, tree.via[a] == a.x, own[a.x], own[a.y])
    if not found[tree.root][1]:
        return head, set()
    for a in tree.order[1:]:
        above = found.get(tree.parent[a])
        if a.ends & q.free and above and tree.via[a] in above[0]:
            at = above[0].index(tree.via[a])
            found[a] = relation(a, [(tree.via[a], {r[at] for r in above[1]}), *((tree.via[c], up[c]) for c in tree.children(a))])
    names, rows = _joined([found[a] for a in tree.order if a in found])
    at = [names.index(v) for v in head]
    return head, {tuple(r[i] for i in at) for r in rows}


def solve(edges: list[tuple], q: PathQuery, heads: list[tuple[str, ...]]) -> set[tuple]:
    """Result of a connected query over one part: bag by bag, then the bags' join."""
    results = []
    for head in heads:
        part = Part(edges)
        own = q.with_head(head)
        atoms, filters, lone, holds = _contracted(part, own, {v: {c} for v, c in q.constants.items()})
        if not holds or not all(lone.values()):
            return set()
        pieces = [((v,), {(x,) for x in s}) for v, s in lone.items()]
        if atoms:
            left = tuple(dict.fromkeys(v for a in atoms for v in (a.x, a.y)))
            kept = tuple(v for v in head if v in left)
            names, rows = _connex(part, (*kept, *(v for v in left if v not in own.free)), atoms, filters)
            pieces.append((kept, {r[: len(kept)] for r in rows}))
        names, rows = _joined(pieces) if pieces else ((), {()})
        if not rows:
            return set()
        at = [names.index(v) for v in head]
        results.append((head, {tuple(r[i] for i in at) for r in rows}))
    names, rows = _joined(results)
    at = [names.index(v) for v in q.head]
    return {tuple(r[i] for i in at) for r in rows}


def evaluate_parts(q: PathQuery, g: LabeledGraph, heads: list[tuple[str, ...]]) -> DataFrame:
    """Result of a connected query over a graph of closed parts; a column `answer` for each part with a match if the head is empty."""
    labels = [x for a in q.atoms for x in letters(a.expr)]
    names = None if any(x.negated for x in labels) or any(nullable(a.expr) for a in q.atoms) else frozenset().union(*(x.labels for x in labels))
    kind = g.vertex_type
    schema = T.StructType([T.StructField(v, kind) for v in q.head] or [T.StructField("answer", T.BooleanType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, edges, out, types = None, [], [], None

        def batch_of(rows: list[tuple]) -> pa.RecordBatch:
            if not q.head:
                return pa.RecordBatch.from_arrays([pa.array([True] * len(rows))], names=["answer"])
            return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], types) for i in range(len(q.head))], names=list(q.head))

        for batch in batches:
            types = batch.schema.field("src").type
            for part, u, label, v in zip(*(batch.column(c).to_pylist() for c in ("part", "src", "label", "dst")), strict=True):
                if part != now:
                    if edges:
                        out.extend(solve(edges, q, heads))
                    now, edges = part, []
                    if len(out) > 20_000:
                        yield batch_of(out)
                        out = []
                edges.append((u, label, v))
        if edges:
            out.extend(solve(edges, q, heads))
        if out:
            yield batch_of(out)

    rows = g.restrict(names).edges.select("part", "src", "label", "dst")
    return rows.repartition("part").sortWithinPartitions("part").mapInArrow(run, schema)
