"""Path expressions over edge labels, and their automata.  Everything here is query-sized and stays on the driver."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable
from dataclasses import dataclass


class PathExpr:
    """A regular expression whose letters are steps over an edge or checks of a vertex."""

    def __str__(self) -> str:
        return _print(self, 0)


@dataclass(frozen=True, repr=False)
class Step(PathExpr):
    """An edge whose label is in `labels`, or not in them if `negated`; walked against its direction if `inverse`."""

    labels: frozenset[str]
    negated: bool = False
    inverse: bool = False


@dataclass(frozen=True, repr=False)
class Guard(PathExpr):
    """Stays at a vertex that the guard of this name contains."""

    name: str


@dataclass(frozen=True, repr=False)
class Empty(PathExpr):
    """No word at all."""


@dataclass(frozen=True, repr=False)
class Epsilon(PathExpr):
    """The walk of no edge."""


@dataclass(frozen=True, repr=False)
class Cat(PathExpr):
    parts: tuple[PathExpr, ...]


@dataclass(frozen=True, repr=False)
class Alt(PathExpr):
    parts: tuple[PathExpr, ...]


@dataclass(frozen=True, repr=False)
class Star(PathExpr):
    inner: PathExpr


def symbol(label: str, inverse: bool = False) -> PathExpr:
    return Step(frozenset([label]), inverse=inverse)


def cat(*parts: PathExpr) -> PathExpr:
    """Concatenation; nested ones are joined, empty words left out, and no word makes no word."""
    flat = [p for x in parts for p in (x.parts if isinstance(x, Cat) else (x,)) if not isinstance(p, Epsilon)]
    if any(isinstance(p, Empty) for p in flat):
        return Empty()
    return flat[0] if len(flat) == 1 else Cat(tuple(flat)) if flat else Epsilon()


def alt(*parts: PathExpr) -> PathExpr:
    """Union; steps in one direction over label sets become one step, and common first or last letters are factored out."""
    flat: list[PathExpr] = []
    for x in parts:
        for p in x.parts if isinstance(x, Alt) else (x,):
            if not isinstance(p, Empty) and p not in flat:
                flat.append(p)
    for inverse in (False, True):
        plain = [p for p in flat if isinstance(p, Step) and not p.negated and p.inverse == inverse]
        if len(plain) > 1:
            merged = Step(frozenset().union(*(p.labels for p in plain)), inverse=inverse)
            flat = [merged if p is plain[0] else p for p in flat if p is plain[0] or p not in plain]
    if not flat:
        return Empty()
    if len(flat) == 1:
        return flat[0]
    if all(isinstance(p, Cat) for p in flat):
        for first, rest in ((0, slice(1, None)), (-1, slice(None, -1))):
            ends = {p.parts[first] for p in flat}
            if len(ends) == 1:
                inner = alt(*(cat(*p.parts[rest]) for p in flat))
                return cat(ends.pop(), inner) if first == 0 else cat(inner, ends.pop())
    if any(isinstance(p, Star) for p in flat):
        flat = [p for p in flat if not isinstance(p, Epsilon)] or [Epsilon()]
    return flat[0] if len(flat) == 1 else Alt(tuple(flat))


def star(inner: PathExpr) -> PathExpr:
    """Repetition; what adds no word is taken out of the inside."""
    if isinstance(inner, Empty | Epsilon | Guard):
        return Epsilon()
    if isinstance(inner, Star):
        return inner
    if isinstance(inner, Alt):
        kept = [p.inner if isinstance(p, Star) else p for p in inner.parts if not isinstance(p, Epsilon | Guard)]
        return Star(alt(*kept)) if kept else Epsilon()
    return Star(inner)


def repeat(inner: PathExpr, least: int, most: int | None) -> PathExpr:
    if most is None:
        return cat(*[inner] * least, star(inner))
    if most < least:
        return Empty()
    tail: PathExpr = Epsilon()
    for _ in range(most - least):
        tail = alt(Epsilon(), cat(inner, tail))
    return cat(*[inner] * least, tail)


def reverse(e: PathExpr) -> PathExpr:
    """The expression of the reversed words; steps keep their direction."""
    return _mirror(e, lambda s: s)


def invert(e: PathExpr) -> PathExpr:
    """The expression of the same walks from their other end: reversed, with each step turned round.  Its own inverse."""
    return _mirror(e, lambda s: Step(s.labels, s.negated, not s.inverse))


def _mirror(e: PathExpr, turn: Callable[[Step], PathExpr]) -> PathExpr:
    if isinstance(e, Step):
        return turn(e)
    if isinstance(e, Cat):
        return cat(*(_mirror(p, turn) for p in reversed(e.parts)))
    if isinstance(e, Alt):
        return alt(*(_mirror(p, turn) for p in e.parts))
    return star(_mirror(e.inner, turn)) if isinstance(e, Star) else e


def compose(first: PathExpr, guard: str | None, second: PathExpr) -> PathExpr:
    """Walks of the first, then of the second, that meet in a vertex of the guard if there is one."""
    return cat(first, Guard(guard), second) if guard else cat(first, second)


def nullable(e: PathExpr) -> bool:
    """Whether the walk of no edge matches.  Guards count as letters, as they hold for some vertices only."""
    if isinstance(e, Cat):
        return all(map(nullable, e.parts))
    if isinstance(e, Alt):
        return any(map(nullable, e.parts))
    return isinstance(e, Epsilon | Star)


def letters(e: PathExpr) -> list[PathExpr]:
    """Steps and guards from left to right."""
    if isinstance(e, Step | Guard):
        return [e]
    if isinstance(e, Star):
        return letters(e.inner)
    return [x for p in getattr(e, "parts", ()) for x in letters(p)]


def _print(e: PathExpr, level: int) -> str:
    if isinstance(e, Step):
        names = sorted(e.labels)
        shown = "|".join(n if re.fullmatch(r"[A-Za-z_]\w*", n) else "'" + n.replace("\\", "\\\\").replace("'", "\\'") + "'" for n in names)
        if e.negated:
            text = f"!({shown})" if names else "."
        else:
            text = shown if len(names) == 1 else f"({shown})"
        return "^" + text if e.inverse else text
    if isinstance(e, Guard):
        return f"[{e.name}]"
    if isinstance(e, Empty):
        return "!()"
    if isinstance(e, Epsilon):
        return "()"
    if isinstance(e, Star):
        return _print(e.inner, 3) + "*"
    sep, own = ("/", 2) if isinstance(e, Cat) else ("|", 1)
    text = sep.join(_print(p, own) for p in e.parts)
    return f"({text})" if level >= own else text


_TOKEN = re.compile(r"\s*(?:(?P<name>[A-Za-z_]\w*)|'(?P<quoted>(?:[^'\\]|\\.)*)'|\[(?P<guard>[^\]]+)\]|\{(?P<low>\d+)(?P<comma>,)?(?P<high>\d+)?\}|(?P<mark>[()|/*+?.^!]))")


def parse_path(text: str) -> PathExpr:
    """Reads labels, '/', '|', '*', '+', '?', '{a,b}', '.', '!(a|b)', '^', '[guard]' and '()' for the empty walk."""
    tokens, at = [], 0
    while text[at:].strip():
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"cannot read {text[at:]!r} in {text!r}")
        tokens.append(m)
        at = m.end()
    tokens.reverse()

    def mark() -> str | None:
        return tokens[-1]["mark"] if tokens else None

    def union() -> PathExpr:
        parts = [chain()]
        while mark() == "|":
            tokens.pop()
            parts.append(chain())
        return alt(*parts)

    def chain() -> PathExpr:
        parts = [repeated()]
        while mark() == "/":
            tokens.pop()
            parts.append(repeated())
        return cat(*parts)

    def repeated() -> PathExpr:
        e = single()
        while tokens and (mark() in ("*", "+", "?") or tokens[-1]["low"]):
            t = tokens.pop()
            if t["low"]:
                low = int(t["low"])
                e = repeat(e, low, (int(t["high"]) if t["high"] else None) if t["comma"] else low)
            else:
                e = {"*": star, "+": lambda x: repeat(x, 1, None), "?": lambda x: alt(Epsilon(), x)}[t["mark"]](e)
        return e

    def single() -> PathExpr:
        if not tokens:
            raise ValueError(f"{text!r} ends too early")
        t = tokens.pop()
        if t["name"] or t["quoted"] is not None:
            return symbol(t["name"] or re.sub(r"\\(.)", r"\1", t["quoted"]))
        if t["guard"]:
            return Guard(t["guard"].strip())
        if t["mark"] == ".":
            return Step(frozenset(), negated=True)
        if t["mark"] == "^":
            return invert(single())
        if t["mark"] == "!":
            inner = single()
            if isinstance(inner, Epsilon):
                return Empty()
            if not isinstance(inner, Step) or inner.negated:
                raise ValueError("'!' stands before labels only")
            return Step(inner.labels, True, inner.inverse)
        if t["mark"] == "(":
            if mark() == ")":
                tokens.pop()
                return Epsilon()
            e = union()
            if mark() != ")":
                raise ValueError(f"a bracket of {text!r} is not closed")
            tokens.pop()
            return e
        raise ValueError(f"{t[0].strip()!r} is out of place in {text!r}")

    out = union()
    if tokens:
        raise ValueError(f"{tokens[-1][0].strip()!r} is out of place in {text!r}")
    return out


@dataclass(frozen=True)
class Automaton:
    """States 0 to `states` - 1, 0 the start; transitions (state, letter, state); no empty transitions."""

    states: int
    finals: frozenset[int]
    transitions: tuple[tuple[int, PathExpr, int], ...]

    @property
    def cyclic(self) -> bool:
        return self.layers() is None

    def layers(self) -> list[int] | None:
        """States in an order in which transitions lead forward; None if there is a cycle."""
        left = dict.fromkeys(range(self.states), 0)
        for q, _, p in self.transitions:
            left[p] += 1
        ready, out = [s for s, n in left.items() if not n], []
        while ready:
            out.append(q := ready.pop())
            for a, _, p in self.transitions:
                if a == q:
                    left[p] -= 1
                    if not left[p]:
                        ready.append(p)
        return out if len(out) == self.states else None

    def labels(self) -> frozenset[str] | None:
        """Labels that some step takes; None if a step takes all but some."""
        steps = [x for _, x, _ in self.transitions if isinstance(x, Step)]
        return None if any(s.negated for s in steps) else frozenset().union(*(s.labels for s in steps)) if steps else frozenset()


def to_automaton(e: PathExpr, deterministic: bool = False, alphabet: Iterable[str] | None = None) -> Automaton:
    """The position automaton, without useless states and with states of equal futures merged.

    deterministic: by subsets, each letter being one label in one direction, or
    one guard; labels that negated steps could take must be given as `alphabet`.
    """
    found: list[PathExpr] = []

    def walk(x: PathExpr) -> tuple[bool, frozenset[int], frozenset[int], frozenset[tuple[int, int]]]:
        """(nullable, first positions, last positions, follow pairs)"""
        none: frozenset = frozenset()
        if isinstance(x, Step | Guard):
            found.append(x)
            here = frozenset([len(found)])
            return False, here, here, none
        if isinstance(x, Star):
            _, first, last, follow = walk(x.inner)
            return True, first, last, follow | {(a, b) for a in last for b in first}
        if isinstance(x, Alt):
            parts = [walk(p) for p in x.parts]
            return any(p[0] for p in parts), none.union(*(p[1] for p in parts)), none.union(*(p[2] for p in parts)), none.union(*(p[3] for p in parts))
        if isinstance(x, Cat):
            empty, first, last, follow = True, none, none, none
            for p in x.parts:
                e2, f2, l2, w2 = walk(p)
                follow = follow | w2 | {(a, b) for a in last for b in f2}
                first = first | f2 if empty else first
                last = last | l2 if e2 else l2
                empty = empty and e2
            return empty, first, last, follow
        return isinstance(x, Epsilon), none, none, none

    empty, first, last, follow = walk(e)
    edges = {(0, found[b - 1], b) for b in first} | {(a, found[b - 1], b) for a, b in follow}
    return _tidy(len(found) + 1, set(last) | ({0} if empty else set()), edges, deterministic, alphabet)


def _tidy(n: int, finals: set[int], edges: set[tuple[int, PathExpr, int]], deterministic: bool, alphabet: Iterable[str] | None) -> Automaton:
    if deterministic:
        n, finals, edges = _subsets(finals, edges, set(alphabet or ()) | {l for _, x, _ in edges if isinstance(x, Step) for l in x.labels})
    reached, stack = {0}, [0]
    while stack:
        q = stack.pop()
        for a, _, p in edges:
            if a == q and p not in reached:
                reached.add(p)
                stack.append(p)
    useful, stack = set(finals & reached), list(finals & reached)
    while stack:
        p = stack.pop()
        for q, _, b in edges:
            if b == p and q in reached and q not in useful:
                useful.add(q)
                stack.append(q)
    edges = {t for t in edges if t[0] in useful and t[2] in useful}
    group = {q: int(q in finals) for q in useful | {0}}
    while True:
        sign = {q: (group[q], frozenset((x, group[p]) for a, x, p in edges if a == q)) for q in group}
        number = {s: i for i, s in enumerate(dict.fromkeys(sign[q] for q in sorted(group)))}
        after = {q: number[sign[q]] for q in group}
        if len(set(after.values())) == len(set(group.values())):
            break
        group = after
    order = {g: i for i, g in enumerate(dict.fromkeys([after[0], *(after[q] for q in sorted(after))]))}
    name = {q: order[after[q]] for q in after}
    out = sorted({(name[a], x, name[p]) for a, x, p in edges}, key=lambda t: (t[0], t[2], str(t[1])))
    return Automaton(len(order), frozenset(name[q] for q in finals if q in name), tuple(out))


def _subsets(finals: set[int], edges: set[tuple[int, PathExpr, int]], alphabet: set[str]) -> tuple[int, set[int], set[tuple[int, PathExpr, int]]]:
    def atoms(x: PathExpr) -> list[PathExpr]:
        if isinstance(x, Guard):
            return [x]
        return [symbol(l, x.inverse) for l in (alphabet - x.labels if x.negated else x.labels)]

    start = frozenset([0])
    number, todo, out = {start: 0}, [start], set()
    while todo:
        now = todo.pop()
        moves: dict[PathExpr, set[int]] = {}
        for a, x, p in edges:
            if a in now:
                for letter in atoms(x):
                    moves.setdefault(letter, set()).add(p)
        for letter, to in moves.items():
            key = frozenset(to)
            if key not in number:
                number[key] = len(number)
                todo.append(key)
            out.add((number[now], letter, number[key]))
    return len(number), {i for s, i in number.items() if s & finals}, out
