"""Joins of materialised relations whose columns are variables."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _tree(columns: list[frozenset[str]]) -> list[tuple[int, int]]:
    """(child, parent) pairs in an order from the root; raises if the relations are not acyclic."""
    done, out = [0], []
    while len(done) < len(columns):
        left = [i for i in range(len(columns)) if i not in done]
        child, parent = max(((i, j) for i in left for j in done), key=lambda ij: len(columns[ij[0]] & columns[ij[1]]))
        done.append(child)
        out.append((child, parent))
    up = dict(out)
    for v in frozenset().union(*columns):
        own = [i for i, c in enumerate(columns) if v in c]
        if sum(up.get(i) not in own for i in own) > 1:
            raise ValueError(f"no join tree: the relations of {v} are not connected")
    return out


def acyclic_join(relations: list[DataFrame], head: list[str], reduced: bool = False) -> DataFrame:
    """The natural join of relations without a cycle, as the distinct values of `head`.

    Unless the inputs are known to have no dangling rows, both passes of
    semi-joins along the join tree come first.  Relations without a common
    column multiply.
    """
    columns = [frozenset(r.columns) for r in relations]
    order = _tree(columns)
    rows = list(relations)
    if not reduced:
        for child, parent in reversed(order):
            if on := sorted(columns[child] & columns[parent]):
                rows[parent] = rows[parent].join(rows[child].select(*on), on, "left_semi")
        for child, parent in order:
            if on := sorted(columns[child] & columns[parent]):
                rows[child] = rows[child].join(rows[parent].select(*on), on, "left_semi")
    return reduce(natural, [rows[0], *(rows[c] for c, _ in order)]).select(*head).distinct()


def natural(a: DataFrame, b: DataFrame) -> DataFrame:
    on = sorted(set(a.columns) & set(b.columns))
    return a.join(b, on) if on else a.crossJoin(b)


def heavy_light_join(a: DataFrame, b: DataFrame, away: str, head: list[str], limit: int) -> DataFrame:
    """Distinct `head` of a joined with b on `away`, which is projected away.

    Values of `away` with more than `limit` rows in b are joined apart, from
    both sides' distinct rows: their many duplicates are met by one partial distinct of their own.
    """
    degree = b.groupBy(away).agg(F.count(F.lit(1)).alias("_n"))
    heavy = degree.where(F.col("_n") > limit).select(away)
    keep = lambda r: [c for c in r.columns if c in head or c == away]
    light = natural(a, b.join(heavy, away, "left_anti")).select(*head).distinct()
    dense = natural(a.join(heavy, away, "left_semi").select(*keep(a)).distinct(), b.join(heavy, away, "left_semi").select(*keep(b)).distinct()).select(*head).distinct()
    return light.union(dense).distinct()
