from __future__ import annotations

import itertools
import re

import pytest
from hypothesis import given, settings
from hypothesis import strategies as s

from regpath.functions.regex import Alt, Cat, Empty, Epsilon, Guard, Star, Step, alt, cat, compose, invert, nullable, parse_path, repeat, reverse, star, symbol, to_automaton

LETTERS = s.sampled_from([symbol("a"), symbol("b"), symbol("a", True), Step(frozenset(), True), Step(frozenset("a"), True), Guard("g"), Epsilon()])
EXPRS = s.recursive(LETTERS, lambda x: s.one_of(s.builds(lambda a, b: cat(a, b), x, x), s.builds(lambda a, b: alt(a, b), x, x), x.map(star)), max_leaves=6)
PLAIN = s.recursive(s.sampled_from([symbol("a"), symbol("b"), Epsilon()]), lambda x: s.one_of(s.builds(lambda a, b: cat(a, b), x, x), s.builds(lambda a, b: alt(a, b), x, x), x.map(star)), max_leaves=6)


def as_re(e):
    if isinstance(e, Step):
        return "[" + "".join(sorted(e.labels)) + "]"
    if isinstance(e, Epsilon):
        return "(?:)"
    if isinstance(e, Empty):
        return "(?!)"
    if isinstance(e, Star):
        return f"(?:{as_re(e.inner)})*"
    sep = "" if isinstance(e, Cat) else "|"
    return "(?:" + sep.join(map(as_re, e.parts)) + ")"


def accepts(a, word):
    now = {0}
    for w in word:
        now = {p for q, x, p in a.transitions if q in now and (w in x.labels) != x.negated}
    return bool(now & a.finals)


@settings(max_examples=150, deadline=None)
@given(EXPRS)
def test_print_and_parse(e):
    assert parse_path(str(e)) == e


@settings(max_examples=150, deadline=None)
@given(EXPRS)
def test_invert_and_reverse_are_involutions(e):
    assert to_words(invert(invert(e))) == to_words(e)
    assert to_words(reverse(reverse(e))) == to_words(e)


def to_words(e, most=3):
    """Accepted letter sequences up to a length."""
    a = to_automaton(e)
    found, layer = set(), {((), 0)}
    for _ in range(most + 1):
        found |= {w for w, q in layer if q in a.finals}
        layer = {((*w, str(x)), p) for w, q in layer for b, x, p in a.transitions if b == q}
    return found


@settings(max_examples=80, deadline=None)
@given(PLAIN)
def test_automaton_against_re(e):
    pattern = re.compile(as_re(e))
    a, d = to_automaton(e), to_automaton(e, deterministic=True)
    for n in range(7):
        for word in itertools.product("ab", repeat=n):
            want = pattern.fullmatch("".join(word)) is not None
            assert accepts(a, word) == want
            assert accepts(d, word) == want
    assert nullable(e) == (pattern.fullmatch("") is not None)
    assert len({(q, l) for q, x, _ in d.transitions for l in x.labels}) == sum(len(x.labels) for _, x, _ in d.transitions)


def test_sugar_and_simplification():
    assert parse_path("a{2,3}") == cat(symbol("a"), symbol("a"), alt(Epsilon(), symbol("a")))
    assert parse_path("a+") == cat(symbol("a"), star(symbol("a")))
    assert parse_path("(a|b)") == Step(frozenset("ab"))
    assert parse_path("^(a/b)") == cat(symbol("b", True), symbol("a", True))
    assert parse_path("!(a|b)") == Step(frozenset("ab"), True)
    assert isinstance(alt(symbol("a"), Epsilon()), Alt)
    assert star(star(symbol("a"))) == star(symbol("a"))
    assert cat(symbol("a"), Empty()) == Empty()
    assert repeat(symbol("a"), 2, 1) == Empty()
    assert parse_path("a/b|a/c") == cat(symbol("a"), Step(frozenset("bc")))
    assert parse_path("'odd label'/[g]") == cat(symbol("odd label"), Guard("g"))
    assert str(compose(symbol("a"), "D", invert(symbol("b")))) == "a/[D]/^b"
    for bad in ("a/", "(a", "a)", "{2}", "a b", "!(a/b)", ""):
        with pytest.raises(ValueError):
            parse_path(bad)


def test_equal_futures_are_merged():
    assert to_automaton(parse_path("(view|click)*/purchase")).states == 2
    assert to_automaton(Empty()).transitions == ()
    assert to_automaton(parse_path("a*")).cyclic and not to_automaton(parse_path("a/b|c")).cyclic
