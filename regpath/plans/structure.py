"""Structure of queries: acyclicity, join trees, elimination, decompositions and widths.  Query-sized, on the driver."""

from __future__ import annotations

import random
from collections import Counter
from dataclasses import dataclass

from regpath.plans.query import Atom, CyclicQueryError, PathQuery

Graph = dict[str, Counter]


def query_graph(q: PathQuery) -> Graph:
    """The undirected multigraph of variables: for each, how many atoms lead to each neighbour (itself too)."""
    g: Graph = {v: Counter() for v in q.vars}
    for a in q.atoms:
        g[a.x][a.y] += 1
        if a.x != a.y:
            g[a.y][a.x] += 1
    return g


def check_acyclic(q: PathQuery) -> None:
    root = {v: v for v in q.vars}

    def find(v: str) -> str:
        while root[v] != v:
            v = root[v]
        return v

    for a in q.atoms:
        x, y = find(a.x), find(a.y)
        if x == y:
            raise CyclicQueryError(f"{a} closes a cycle")
        root[x] = y


def trees(q: PathQuery) -> list[list[Atom]]:
    """Atoms by connected part, in the order of the body."""
    out: list[list[Atom]] = []
    for a in q.atoms:
        touching = [t for t in out if any(b.ends & a.ends for b in t)]
        out = [t for t in out if not any(t is s for s in touching)] + [[b for t in touching for b in t] + [a]]
    return [[a for a in q.atoms if any(a is b for b in t)] for t in out]


def _linked(vertices: set[str], atoms) -> bool:
    """Whether atoms within `vertices` connect them."""
    if not vertices:
        return True
    seen, todo = set(), [min(vertices)]
    while todo:
        if (v := todo.pop()) not in seen:
            seen.add(v)
            todo += [a.other(v) for a in atoms if v in a.ends and a.ends <= vertices]
    return seen == vertices


def is_free_connex(q: PathQuery) -> bool:
    """In each tree of an acyclic query, the free variables are connected by atoms among themselves."""
    check_acyclic(q)
    return all(_linked({v for a in t for v in a.ends} & q.free, t) for t in trees(q))


@dataclass(frozen=True)
class JoinTree:
    """Atoms with their parents; children share one variable, `via`, with their parent."""

    root: Atom
    parent: dict[Atom, Atom]
    via: dict[Atom, str]
    order: tuple[Atom, ...]

    def children(self, a: Atom) -> list[Atom]:
        return [c for c in self.order if self.parent.get(c) is a]


def free_top_join_tree(q: PathQuery, atoms: list[Atom] | None = None, root: Atom | None = None) -> JoinTree:
    """A join tree of one connected part whose atoms with free variables are on top, the root among them.

    Any atom that touches a free variable may be the root; by default the first
    with most of them.  Grown from the root over shared variables: a new atom
    hangs on the atom through which its variable was reached.  In a free-connex
    query an atom with a free variable is then only reached through free variables.
    """
    atoms = list(q.atoms) if atoms is None else atoms
    if root is None:
        root = max(atoms, key=lambda a: len(a.ends & q.free))
    elif any(a.ends & q.free for a in atoms) and not root.ends & q.free:
        raise ValueError("the root must touch a free variable")
    parent, via, order, seen = {}, {}, [root], set(root.ends)
    owner = {v: root for v in root.ends}
    todo = sorted(root.ends, key=lambda v: v not in q.free)
    while todo:
        v = todo.pop(0)
        for a in atoms:
            if v in a.ends and a not in order:
                parent[a], via[a] = owner[v], v
                order.append(a)
                o = a.other(v)
                if o not in seen:
                    seen.add(o)
                    owner[o] = a
                    todo.append(o)
    return JoinTree(root, parent, via, tuple(order))


def is_free_top(q: PathQuery, tree: JoinTree) -> bool:
    """Whether each atom with a free variable hangs on another such atom."""
    return all(tree.parent[a].ends & q.free for a in tree.order if a.ends & q.free and a is not tree.root)


def eliminate(g: Graph, v: str, keep=frozenset()) -> Graph:
    """Takes out a vertex of degree 1, or of degree 2 by linking its neighbours; so goes an isolated neighbour not in `keep`."""
    out = {u: Counter(n) for u, n in g.items()}
    around = list(out.pop(v).elements())
    for u in around:
        out[u][v] -= 1
        out[u] = +out[u]
    if len(around) == 2:
        a, b = around
        out[a][b] += 1
        out[b][a] += 1
    elif len(around) == 1:
        if not out[around[0]] and around[0] not in keep:
            del out[around[0]]
    else:
        raise ValueError(f"{v} has degree {len(around)}")
    return out


def elimination_order(q: PathQuery, policy="leaves_first") -> tuple[list[str], Graph]:
    """(order, contracted graph): bound variables of degree 1 or 2 until none is left.

    policy: 'leaves_first', 'paths_first', 'random', or variables to prefer in
    their order.  The graph is the same for all; the order fixes the work.
    """
    g, order = query_graph(q), []
    rng = random.Random(0)
    while True:
        ready = [v for v in g if v not in q.free and 1 <= sum(g[v].values()) <= 2]
        if not ready:
            return order, g
        if policy == "random":
            v = rng.choice(ready)
        elif policy in ("leaves_first", "paths_first"):
            v = min(ready, key=lambda u: (sum(g[u].values()) != (1 if policy == "leaves_first" else 2), list(q.vars).index(u)))
        else:
            v = min(ready, key=lambda u: list(policy).index(u) if u in policy else len(list(policy)))
        g = eliminate(g, v, q.free)
        order.append(v)


def contracted_graph(q: PathQuery) -> Graph:
    return elimination_order(q)[1]


def promoted(q: PathQuery) -> list[str]:
    """Bound variables that contraction leaves: they have degree 3 or more."""
    return [v for v in contracted_graph(q) if v not in q.free]


@dataclass(frozen=True)
class Decomposition:
    """Bags of variables on the nodes of a tree, given by pairs of node numbers."""

    bags: tuple[frozenset[str], ...]
    edges: tuple[tuple[int, int], ...]

    def validate(self, q: PathQuery) -> None:
        """Raises unless this is a free-connex tree decomposition of q."""
        n = len(self.bags)
        if len(self.edges) != n - 1 or not self._joined(set(range(n))):
            raise ValueError("the bags do not form a tree")
        for a in q.atoms:
            if not any(a.ends <= b for b in self.bags):
                raise ValueError(f"no bag covers {a}")
        for v in q.vars:
            if not self._joined({i for i in range(n) if v in self.bags[i]}):
                raise ValueError(f"the bags of {v} are not connected")
        if self.free_core(q) is None:
            raise ValueError("no connected bags have exactly the free variables: the decomposition is not free-connex")

    def free_core(self, q: PathQuery) -> set[int] | None:
        """A connected set of nodes whose bags' union is the free variables; empty without free variables."""
        inside = {i for i, b in enumerate(self.bags) if b <= q.free}
        if not q.free:
            return set()
        while inside:
            part, todo = set(), [min(inside)]
            while todo:
                if (i := todo.pop()) in inside and i not in part:
                    part.add(i)
                    todo += [b if a == i else a for a, b in self.edges if i in (a, b)]
            if frozenset().union(*(self.bags[i] for i in part)) == q.free:
                return part
            inside -= part
        return None

    def _joined(self, nodes: set[int]) -> bool:
        if not nodes:
            return True
        seen, todo = set(), [min(nodes)]
        while todo:
            if (i := todo.pop()) in nodes and i not in seen:
                seen.add(i)
                todo += [b if a == i else a for a, b in self.edges if i in (a, b)]
        return seen == nodes


def pieces(q: PathQuery) -> list[tuple[frozenset[str], frozenset[str]]]:
    """(variables, free variables among them) of each largest set of atoms that bound variables link."""
    groups: list[list[Atom]] = []
    for a in q.atoms:
        touching = [g for g in groups if any(b.ends & a.ends - q.free for b in g)]
        groups = [g for g in groups if not any(g is t for t in touching)] + [[b for t in touching for b in t] + [a]]
    out = [frozenset(v for a in g for v in a.ends) for g in groups]
    return [(p, p & q.free) for p in out]


def canonical_decomposition(q: PathQuery) -> Decomposition:
    """For each piece a core bag of its free variables, and a bag of all its variables on it; of least width."""
    parts = sorted(pieces(q), key=lambda p: sorted(p[0]))
    cores = [f for _, f in parts]
    n = len(parts)
    bags = [*cores, *(p for p, _ in parts)]
    edges, root = [(i, n + i) for i in range(n)], list(range(n))
    for i, j in sorted(((i, j) for i in range(n) for j in range(i)), key=lambda ij: -len(cores[ij[0]] & cores[ij[1]])):
        if root[i] != root[j]:
            edges.append((i, j))
            root = [root[j] if r == root[i] else r for r in root]
    return Decomposition(tuple(bags), tuple(edges))


def ctw_of(q: PathQuery, d: Decomposition) -> int:
    """Most bound variables that survive contraction in a bag's induced query."""
    return max((len([v for v in promoted(q.induced(b)) if v not in b]) for b in d.bags), default=0)


def ctw(q: PathQuery) -> int:
    return ctw_of(q, canonical_decomposition(q))


def fhtw(q: PathQuery) -> int:
    """Free-connex fractional hypertree width of an acyclic query of binary atoms."""
    return max([1, *(len(f) for p, f in pieces(q) if p - f)])
