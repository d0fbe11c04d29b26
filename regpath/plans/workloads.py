"""The workloads: worked examples and named classes of queries, on the graphs of the given tables."""

from __future__ import annotations

from regpath.plans.query import PathQuery, parse_query

#: name: (graph, query).  Variables and shapes follow the examples; labels are of the tables.
TEXTS = {
    "four_atoms": ("timeline", "X, Y, U <- [.*/purchase](X, Y), [error](Y, Z), [signup](Z, W), [click](X, U)"),
    "five_atoms": ("supply", "A, B, D <- [placed/contains_R](A, B), [supplied_by/s_in](B, C), [supplied_by](B, D), [c_in](A, E), [part_of](E, F)"),
    "nine_atoms": (
        "timeline",
        "A, C, E, G, H <- [(view|click)*/purchase](A, B), [(view|click)*](B, C), [(view|click)*](B, D), [(view|purchase)*](E, D), "
        "[(error|signup)*/click](A, F), [(error|signup)*](F, G), [(view|purchase)*](F, H), [.*/error](F, I), [signup](I, J)",
    ),
    "path_k1": ("supply", "A, B <- [placed](A, B)"),
    "path_k2": ("supply", "A, C <- [placed](A, B), [contains_R](B, C)"),
    "path_k3": ("supply", "A, D <- [placed](A, B), [contains_R](B, C), [supplied_by](C, D)"),
    "path_k4": ("supply", "A, E <- [placed](A, B), [contains_R](B, C), [supplied_by](C, D), [s_in](D, E)"),
    "path_k5": ("supply", "A, F <- [placed](A, B), [contains_R](B, C), [supplied_by](C, D), [s_in](D, E), [part_of](E, F)"),
    "path_join_vars_free": ("supply", "B, C <- [placed](A, B), [contains_R](B, C), [supplied_by](C, D)"),
    "star2": ("supply", "A, C <- [placed](A, B), [contains_R](B, C)"),
    "star3": ("supply", "A, C, E <- [placed](A, B), [contains_R](B, C), [contains_A](B, E)"),
    "star4": ("supply", "A, C, E, F <- [placed](A, B), [contains_R](B, C), [contains_A](B, E), [contains_N](B, F)"),
    "boolean": ("timeline", " <- [.*/purchase](X, Y), [error](Y, Z)"),
    "forest": ("supply", "X, U <- [part_of](X, Y), [s_in](U, V)"),
    "dangling": ("timeline", "X, Y, U <- [purchase](X, Y), [.*](Y, U), [signup/signup](U, W)"),
    "composite_leaf": ("supply", "X <- [placed](X, Y), [contains_R](Y, Z)"),
    "replaced_atom": ("timeline", "X, Y, U <- [.*](X, M), [.](M, N), [purchase](N, Y), [error](Y, Z), [signup](Z, W), [click](X, U)"),
    "full": ("timeline", "X, Y, Z, W, U <- [.*/purchase](X, Y), [error](Y, Z), [signup](Z, W), [click](X, U)"),
}


def workload(name: str) -> PathQuery:
    return parse_query(TEXTS[name][1])
