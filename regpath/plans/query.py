"""Queries: a head of free variables and a body of path atoms."""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace

from regpath.functions.regex import PathExpr, parse_path


class CyclicQueryError(ValueError):
    """The query graph has a cycle, two atoms on one pair of variables, or an atom from a variable to itself."""


@dataclass(frozen=True)
class Atom:
    """Walks of `expr` from the value of x to the value of y."""

    expr: PathExpr
    x: str
    y: str

    @property
    def ends(self) -> frozenset[str]:
        return frozenset((self.x, self.y))

    def other(self, var: str) -> str:
        return self.y if var == self.x else self.x

    def __str__(self) -> str:
        return f"[{self.expr}]({self.x}, {self.y})"


@dataclass(frozen=True)
class PathQuery:
    """head: free variables in the order of the result's columns; constants: variables fixed to one vertex."""

    head: tuple[str, ...]
    atoms: tuple[Atom, ...]
    constants: dict[str, object] = field(default_factory=dict)

    @staticmethod
    def of(head, atoms, constants: dict[str, object] | None = None) -> PathQuery:
        """Atoms as (expression or its text, x, y)."""
        made = tuple(a if isinstance(a, Atom) else Atom(parse_path(a[0]) if isinstance(a[0], str) else a[0], a[1], a[2]) for a in atoms)
        q = PathQuery(tuple(head), made, dict(constants or {}))
        if missing := [v for v in q.head if v not in q.vars]:
            raise ValueError(f"free variables in no atom: {missing}")
        if len({v.lower() for v in q.vars}) < len(q.vars) or len(set(q.head)) < len(q.head):
            raise ValueError("variables must differ by more than case, and stand once in the head")
        return q

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for a in self.atoms for v in (a.x, a.y)))

    @property
    def free(self) -> frozenset[str]:
        return frozenset(self.head)

    @property
    def bound(self) -> tuple[str, ...]:
        return tuple(v for v in self.vars if v not in self.free)

    @property
    def is_full(self) -> bool:
        return not self.bound

    def at(self, var: str) -> list[Atom]:
        return [a for a in self.atoms if var in a.ends]

    def with_head(self, head) -> PathQuery:
        return replace(self, head=tuple(head))

    def induced(self, bag) -> PathQuery:
        """The same body with the free variables of a bag."""
        return self.with_head(v for v in self.head if v in set(bag))

    def __str__(self) -> str:
        return f"{', '.join(self.head)} <- {', '.join(map(str, self.atoms))}"


_ATOM = re.compile(r"\s*\[((?:'(?:[^'\\]|\\.)*'|\[[^\]]*\]|[^\[\]'])*)\]\s*\(\s*('[^']*'|-?\d+|\w+)\s*,\s*('[^']*'|-?\d+|\w+)\s*\)\s*(,|$)")


def parse_query(text: str) -> PathQuery:
    """Reads `X, Y <- [expression](X, Z), [expression](Z, Y)`; a quoted text or number as an end is a constant."""
    head, arrow, body = text.partition("<-")
    if not arrow:
        raise ValueError("a query is `variables <- [expression](X, Y), ...`")
    atoms, constants, at = [], {}, 0
    while body[at:].strip():
        m = _ATOM.match(body, at)
        if not m:
            raise ValueError(f"cannot read {body[at:]!r}")
        ends = []
        for end in (m[2], m[3]):
            if end[0] in "'-0123456789":
                name = f"const{len(constants)}"
                constants[name] = end[1:-1] if end[0] == "'" else int(end)
                end = name
            ends.append(end)
        atoms.append((m[1], *ends))
        at = m.end()
    return PathQuery.of([v.strip() for v in head.split(",") if v.strip()], atoms, constants)
