"""One path expression under vertex filters: the primitive on which all evaluation rests.

Three ways give the same result.  `unrolled`: an expression without
repetition is one plan of joins, a join and a distinct for each state.
`local`: in a graph of small closed parts, each part is searched within one task; larger parts go by rounds.
`rounds`: any graph, a job for each step of all walks at once.

What holds for `rounds`: every row of a search is made once, and pairs of both ends stay within
edges times the root of the result.  But each round reads the steps once, and the rows found so far once, so that
reading is rounds times these: long walks over one giant component are the costly case.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from regpath.functions.regex import Automaton, Guard, PathExpr, Step, invert, nullable, to_automaton
from regpath.operators.scratch import Scratch
from regpath.sources.graph import LabeledGraph


#: Pairs that a task hands on at once.
ROWS_AT_ONCE = 50_000
#: Two steps go by least middles if their walks are so many times the vertices beside edges that takes, and so many at least.
WALKS_FOR_MIDDLES, LEAST_WALKS = 4, 1_000_000
#: Walks through one middle that a task makes at once.
WALKS_A_TASK = 1 << 22
#: Tasks that these are dealt to, at most.
MOST_TASKS = 10_000
#: Rounds after which the files of all rounds so far are written as one table.
COMPACT = 32


@dataclass
class Evaluation:
    """How expressions are evaluated, and what was done.

    mode: 'auto' or one of the three ways.  cap: targets a vertex may hold in the
    capped search, 'auto' to start at 16; it doubles as needed.  one_part: a part of up to so many edges
    and possible pairs is searched within a task; a graph
    without parts counts as one part in itself, and goes another way if it is larger, whatever the mode.  budget: the
    greatest bound that a query may have.  direction: of searches for pairs, 'forward',
    'backward', or 'auto' for backward where only the far end has a filter.  log: a dict of each evaluation.
    """

    scratch: Scratch
    mode: str = "auto"
    cap: int | str = "auto"
    max_rounds: int = 1_000_000
    one_part: tuple[int, int] = (50_000, 25_000_000)
    budget: float | None = None
    direction: str = "auto"
    log: list[dict] = field(default_factory=list)
    _large: dict = field(default_factory=dict)
    _small: dict = field(default_factory=dict)

    def way(self, g: LabeledGraph, a: Automaton) -> str:
        if self.mode == "local" and not g.parted and not self.small_enough(g):
            return "rounds" if a.cyclic else "unrolled"
        if self.mode != "auto":
            return self.mode
        if not a.cyclic:
            return "unrolled"
        return "local" if g.parted or self.small_enough(g) else "rounds"

    def small_enough(self, g: LabeledGraph) -> bool:
        """Whether a graph without parts can be searched within a task: told by its edges, read no further than the bound, and ends.  Once for each graph."""
        if id(g.edges) not in self._small:
            most, pairs = self.one_part
            few = g.edges.limit(most + 1)
            n, a, b = few.agg(F.count(F.lit(1)), F.count_distinct("src"), F.count_distinct("dst")).first()
            self._small[id(g.edges)] = (g.edges, n <= most and max(a, b) ** 2 <= pairs)
        return self._small[id(g.edges)][1]

    def large_parts(self, g: LabeledGraph) -> DataFrame | None:
        """(part): parts too large for a task; None if there are none.  Counted once for each graph."""
        if id(g.edges) not in self._large:
            most, pairs = self.one_part
            large = g.edges.groupBy("part").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > min(most, math.isqrt(pairs))).select("part")
            self._large[id(g.edges)] = (g.edges, self.scratch.table(large) if holds(large) else None)  # the graph is held, so that no other gets its id
        return self._large[id(g.edges)][1]

    def note(self, **what) -> None:
        self.log.append(what)


def both_of(filters: list[DataFrame]) -> DataFrame | None:
    """Vertices that every filter has; None for no filter."""
    out = None
    for f in filters:
        out = f.select("v").distinct() if out is None else out.join(f.select("v"), "v", "left_semi")
    return out


def holds(df: DataFrame) -> bool:
    """Whether a relation has a row; stops at the first."""
    return bool(df.limit(1).take(1))


def reach_unary(g: LabeledGraph, e: PathExpr, keep: str, x_in=(), y_in=(), require: bool = True, how: Evaluation | None = None) -> DataFrame:
    """(v): values of one end of `e`, the other being any vertex of its filters.  Work is linear in the edges."""
    how = how or Evaluation(Scratch(g.edges.sparkSession, "reach"))
    x, y = both_of(list(x_in)), both_of(list(y_in))
    if keep == "x":
        e, x, y = invert(e), y, x
    a = to_automaton(e)
    if not require:
        return _no_vertex(g)
    way = how.way(g, a)
    if way == "unrolled":
        reached = _unrolled(g, a, x, tagged=False, targets=y)
    elif way == "local":
        reached = _by_parts(g, a, x, y, how, tagged=False)
    else:
        reached = _rounds(g, a, x, y, how)
    out = reached if y is None else reached.join(y, "v", "left_semi")
    if nullable(e):
        stay = g.vertices().select("v")
        for f in (x, y):
            stay = stay if f is None else stay.join(f, "v", "left_semi")
        out = out.union(stay)
    return out.distinct()


def reach_nullary(g: LabeledGraph, e: PathExpr, x_in=(), y_in=(), require: bool = True, how: Evaluation | None = None) -> bool:
    """Whether some walk of `e` leads from a vertex of the x filters to one of the y filters."""
    return require and holds(reach_unary(g, e, "y", x_in, y_in, True, how))


def pairs_capped(g: LabeledGraph, e: PathExpr, x_in=(), y_in=(), require: bool = True, how: Evaluation | None = None) -> DataFrame:
    """(x, y): both ends of `e` under the filters; work follows the edges and the size of the result."""
    how = how or Evaluation(Scratch(g.edges.sparkSession, "reach"))
    if not require:
        return _no_vertex(g).select(F.col("v").alias("x"), F.col("v").alias("y"))
    if how.direction == "backward" or how.direction == "auto" and not x_in and (y_in or _fewer_targets(g, to_automaton(e), how)):
        turned = pairs_capped(g, invert(e), y_in, x_in, True, replace(how, direction="forward"))
        return turned.select(F.col("y").alias("x"), F.col("x").alias("y"))
    x, y, a = both_of(list(x_in)), both_of(list(y_in)), to_automaton(e)
    way = how.way(g, a)
    if way == "unrolled":
        if (found := _by_middles(g, a, x, y, how)) is not None:
            return found
        found = _unrolled(g, a, x, tagged=True, targets=y)
    elif way == "local":
        found = _by_parts(g, a, x, y, how, tagged=True)
    else:
        found = _capped(g, a, x, y, how)
    found = found if y is None else found.join(y, "v", "left_semi").select("s", "v")
    if nullable(e):
        stay = g.vertices().select("v")
        for f in (x, y):
            stay = stay if f is None else stay.join(f, "v", "left_semi")
        found = found.union(stay.select(F.col("v").alias("s"), "v"))
    return found.select(F.col("s").alias("x"), F.col("v").alias("y")).distinct()


def _fewer_targets(g: LabeledGraph, a: Automaton, how: Evaluation) -> bool:
    """For an expression of three letters and more without repetition: whether fewer vertices can end than can start a walk.

    Rows in between are pairs with the end from which the search goes, so the
    smaller side keeps them few.  One pass over the edges, with estimated counts.
    """
    order = a.layers()
    if how.mode not in ("auto", "unrolled") or order is None or a.states < 4:
        return False
    first = [x for q, x, _ in a.transitions if q == 0 and isinstance(x, Step)]
    last = [x for _, x, p in a.transitions if p in a.finals and isinstance(x, Step)]
    if not first or not last or a.finals & {0}:
        return False

    def ends(steps: list[Step], start: bool):
        out = None
        for s in steps:
            column = F.col("src" if start != (s.inverse and not g.closed) else "dst")
            one = F.when(g.takes(s), column)
            out = one if out is None else F.coalesce(out, one)
        return F.approx_count_distinct(out)

    n = g.edges.agg(ends(first, True), ends(last, False)).first()
    return n[1] < n[0]


def _no_vertex(g: LabeledGraph) -> DataFrame:
    return g.edges.where(F.lit(False)).select(F.col("src").alias("v"))


# ---- one plan


def _unrolled(g: LabeledGraph, a: Automaton, sources: DataFrame | None, tagged: bool, targets: DataFrame | None) -> DataFrame:
    """(v) or (s, v) behind at least one letter, state by state; states lead forward only.

    Tagged rows are first cut to the vertices from which a target, or without a filter any end, can still be
    reached, so that no more rows are made than lead on.  States next to the start need no such cut
    without a filter: their rows are edges.
    """
    order = a.layers()
    if order is None:
        raise ValueError("an expression with repetition has no unrolled plan")
    columns = ["s", "v"] if tagged else ["v"]
    near = {p for q, _, p in a.transitions if q == 0} if targets is None else set()
    useful = {}
    if tagged and (targets is not None or any(q not in near and q not in a.finals for q in order if q)):
        useful = {p: df for p, df in _leading(g, a, order, targets).items() if df is not None and p not in near}

    def entered(letter) -> DataFrame:
        """(u, v) of a letter."""
        return g.guards[letter.name].select(F.col("v").alias("u"), "v") if isinstance(letter, Guard) else g.walked(letter)

    at: dict[int, DataFrame] = {}
    for p in order:
        arrived = None
        for q, letter, to in a.transitions:
            if to != p:
                continue
            moves = entered(letter)
            if q == 0:
                made = moves if sources is None else moves.join(sources.withColumnRenamed("v", "u"), "u", "left_semi")
                made = made.select(F.col("u").alias("s"), "v") if tagged else made.select("v")
            else:
                made = at[q].withColumnRenamed("v", "u").join(moves, "u").select(*columns)
            if p in useful:
                made = made.join(useful[p], "v", "left_semi").select(*columns)
            arrived = made if arrived is None else arrived.union(made)
        if arrived is not None:
            at[p] = arrived.distinct()
    out = None
    for p in sorted(a.finals - {0}):
        out = at[p] if out is None else out.union(at[p])
    if out is None:
        none = _no_vertex(g)
        return none.select(F.col("v").alias("s"), "v") if tagged else none
    return out


def _by_middles(g: LabeledGraph, a: Automaton, sources: DataFrame | None, targets: DataFrame | None, how: Evaluation) -> DataFrame | None:
    """(x, y), each once, of two steps whose walks are far more than their edges; None for other expressions and graphs.

    A pair is made at the least of the middles that it has.  Each edge brings the lesser middles of its
    own end: if two edges that meet have one in common, their pair is made there.  So walks are
    neither shuffled nor held.  The edges of a frequent middle are dealt to a grid of tasks.
    """
    if len(a.transitions) != 2 or len(a.finals) != 1 or 0 in a.finals:
        return None
    (q1, one, p1), (q2, two, p2) = sorted(a.transitions, key=lambda t: t[0] != 0)
    if q1 != 0 or p1 != q2 or p2 not in a.finals or p1 in a.finals or not isinstance(one, Step) or not isinstance(two, Step):
        return None
    left, right = g.walked(one).select(F.col("u").alias("e"), F.col("v").alias("m")), g.walked(two).select(F.col("v").alias("e"), F.col("u").alias("m"))
    if sources is not None:
        left = left.join(sources.select(F.col("v").alias("e")), "e", "left_semi")
    if targets is not None:
        right = right.join(targets.select(F.col("v").alias("e")), "e", "left_semi")
    both = left.select("*", F.lit(0).alias("side")).union(right.select("*", F.lit(1).alias("side"))).distinct()
    n = [F.count(F.when(F.col("side") == i, 1)) for i in (0, 1)]
    middles = both.groupBy("m").agg(n[0].alias("n0"), n[1].alias("n1")).where("n0 > 0 and n1 > 0")
    walks = middles.agg(F.coalesce(F.sum(F.col("n0").cast("double") * F.col("n1")), F.lit(0.0))).first()[0]
    if walks < LEAST_WALKS:
        return None
    beside = both.groupBy("e", "side").count().agg(F.sum(F.col("count").cast("double") * F.col("count"))).first()[0]
    if walks < WALKS_FOR_MIDDLES * beside:
        return None
    grid = F.ceil(F.sqrt(F.col("n0").cast("double") * F.col("n1") / WALKS_A_TASK)).cast("int")
    grids = how.scratch.table(middles.select("m", grid.alias("grid")))
    own = both.join(grids, "m")  # only middles with edges on both sides can be common
    held = own.groupBy("e", "side").agg(F.sort_array(F.collect_list(F.struct("m", "grid"))).alias("ms"))
    at = held.select("e", "side", F.col("ms.m").alias("ms"), F.posexplode("ms").alias("i", "x")).select("e", "side", F.col("x.m").alias("m"), F.col("x.grid").alias("grid"), F.slice("ms", F.lit(1), F.col("i")).alias("before"))
    row = F.pmod(F.xxhash64("e"), F.col("grid")).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.col("grid") - 1))
    # written, as both sides are read from it
    at = how.scratch.table(at.select("side", "e", "m", "before", row.alias("own"), every.alias("other")))
    first = at.where("side = 0").select("m", F.col("own").alias("i"), F.col("other").alias("j"), F.col("e").alias("x"), F.col("before").alias("_bx"))
    second = at.where("side = 1").select("m", F.col("other").alias("i"), F.col("own").alias("j"), F.col("e").alias("y"), F.col("before").alias("_by"))
    how.note(stage="middles", walks=walks, beside=beside)
    # dealt by number: few bytes go in and many pairs come out, which adaptive execution cannot see
    tasks = int(max(int(at.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(walks / WALKS_A_TASK, MOST_TASKS)))
    first, second = (df.repartition(tasks, "m", "i", "j") for df in (first, second))
    return first.hint("shuffle_hash").join(second, ["m", "i", "j"]).where(~F.arrays_overlap("_bx", "_by")).select("x", "y")


def _leading(g: LabeledGraph, a: Automaton, order: list[int], targets: DataFrame | None) -> dict[int, DataFrame | None]:
    """For each state but the start: vertices from which walks lead on to a target; None for all, at final states without a filter."""
    out: dict[int, DataFrame | None] = {}
    for q in reversed(order):
        if q == 0:
            continue
        if q in a.finals and targets is None:
            out[q] = None
            continue
        found = targets if q in a.finals else None
        for b, letter, p in a.transitions:
            if b == q:
                moves = g.guards[letter.name].select(F.col("v").alias("u"), "v") if isinstance(letter, Guard) else g.walked(letter)
                back = (moves if out[p] is None else moves.join(out[p], "v", "left_semi")).select(F.col("u").alias("v"))
                found = back if found is None else found.union(back)
        out[q] = found.distinct()
    return out


# ---- within parts


def _by_parts(g: LabeledGraph, a: Automaton, sources: DataFrame | None, targets: DataFrame | None, how: Evaluation, tagged: bool) -> DataFrame:
    """(v) or (s, v): small parts each within a task, large ones by rounds."""
    large = how.large_parts(g) if g.parted and how.mode == "auto" else None
    if large is None:
        return _local(g, a, sources, targets, tagged)
    small = replace(g, edges=g.edges.join(F.broadcast(large), "part", "left_anti").select(*g.edges.columns))
    rest = replace(g, edges=g.edges.join(F.broadcast(large), "part", "left_semi").select("src", "label", "dst"))
    ends = rest.vertices()
    rest = replace(rest, guards={n: v.join(ends, "v", "left_semi") for n, v in g.guards.items()})
    beyond = _capped(rest, a, sources, targets, how).select("s", "v") if tagged else _rounds(rest, a, sources, targets, how).select("v")
    return _local(small, a, sources, targets, tagged).union(beyond)


def _local(g: LabeledGraph, a: Automaton, sources: DataFrame | None, targets: DataFrame | None, tagged: bool) -> DataFrame:
    """(v) or (s, v): each part's steps and filters meet in one task, which walks them there."""
    if not g.parted:
        g = replace(g, edges=g.edges.withColumn("part", F.lit(0)))
    steps = g.step_relation(a).select("part", F.lit(0).alias("kind"), "u", "q", "v", "p")
    rows = steps
    for kind, vertices in ((1, sources), (2, targets)):
        if vertices is not None:
            own = g.vertices().join(vertices, "v", "left_semi")
            rows = rows.union(own.select("part", F.lit(kind).alias("kind"), F.col("v").alias("u"), F.lit(0).alias("q"), "v", F.lit(0).alias("p")))
    kind = g.vertex_type
    schema = T.StructType([T.StructField("s", kind), T.StructField("v", kind)] if tagged else [T.StructField("v", kind)])
    walked = rows.repartition("part").sortWithinPartitions("part").mapInArrow(_walker(a.finals, sources is not None, targets is not None, tagged), schema)
    return walked


def _walker(finals: frozenset[int], with_sources: bool, with_targets: bool, tagged: bool):
    def settle(steps: list, sources: set, targets: set) -> Iterator[tuple]:
        ahead: dict = {}
        for u, q, v, p in steps:
            ahead.setdefault((u, q), []).append((v, p))
        starts = sorted({u for u, q in ahead if q == 0 and (not with_sources or u in sources)})
        if tagged and with_targets:
            behind: dict = {}
            for node, to in ahead.items():
                for n in to:
                    behind.setdefault(n, []).append(node)
            useful = {n for n in behind if n[1] in finals and n[0] in targets}
            todo = list(useful)
            while todo:
                for n in behind.get(todo.pop(), ()):
                    if n not in useful:
                        useful.add(n)
                        todo.append(n)
            ahead = {n: [m for m in to if m in useful] for n, to in ahead.items() if n in useful}
        for group in ([s] for s in starts) if tagged else [starts]:
            todo = [(s, 0) for s in group]
            seen, out = set(), set()
            while todo:
                for n in ahead.get(todo.pop(), ()):
                    if n not in seen:
                        seen.add(n)
                        todo.append(n)
                        if n[1] in finals and (not with_targets or n[0] in targets):
                            out.add(n[0])
            yield from ((group[0], v) for v in out) if tagged else ((v,) for v in out)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = None

        def parts() -> Iterator[Iterator[tuple]]:
            nonlocal kind
            now, steps, sources, targets = None, [], set(), set()
            for batch in batches:
                kind = batch.schema.field("u").type
                for part, what, u, q, v, p in zip(*(batch.column(c).to_pylist() for c in ("part", "kind", "u", "q", "v", "p")), strict=True):
                    if part != now:
                        yield settle(steps, sources, targets)
                        now, steps, sources, targets = part, [], set(), set()
                    if what == 0:
                        steps.append((u, q, v, p))
                    else:
                        (sources if what == 1 else targets).add(u)
            yield settle(steps, sources, targets)

        rows = itertools.chain.from_iterable(parts())  # pairs are handed on while a part is walked, never held all at once
        while out := list(itertools.islice(rows, ROWS_AT_ONCE)):
            yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in out], kind) for c in range(2 if tagged else 1)], names=["s", "v"] if tagged else ["v"])

    return run


# ---- a job for each step


def _start(steps: DataFrame, sources: DataFrame | None) -> DataFrame:
    """(v) with a first step, within the sources."""
    first = steps.where("q = 0").select(F.col("u").alias("v")).distinct()
    return first if sources is None else first.join(sources, "v", "left_semi")


def _spread(first: DataFrame, steps: DataFrame, key: list[str], how: Evaluation) -> tuple[DataFrame, int]:
    """All rows that steps lead to from the first, written round by round; and the rounds.

    key: columns that go with a walk.  Only new rows go on; all rows found so far are read as one table of many files.
    """
    spark, scratch = steps.sparkSession, how.scratch
    paths = [scratch.path(first)]
    frontier = spark.read.schema(first.schema).parquet(paths[0])
    rounds = 0
    while rounds < how.max_rounds:
        known = spark.read.schema(first.schema).parquet(*paths)
        moved = frontier.select(*key, F.col("v").alias("u"), "q").join(steps, ["u", "q"]).select(*key, "v", F.col("p").alias("q")).distinct()
        paths.append(scratch.path(moved.join(known, [*key, "v", "q"], "left_anti").select(*key, "v", "q")))
        frontier = spark.read.schema(first.schema).parquet(paths[-1])
        rounds += 1
        if not holds(frontier):
            break
        if len(paths) > COMPACT:
            paths = [scratch.path(spark.read.schema(first.schema).parquet(*paths[:-1])), paths[-1]]
    return spark.read.schema(first.schema).parquet(*paths[:-1]), rounds


def _rounds(g: LabeledGraph, a: Automaton, sources: DataFrame | None, targets: DataFrame | None, how: Evaluation) -> DataFrame:
    steps = how.scratch.table(g.step_relation(a).select("u", "q", "v", "p"))
    first = _start(steps, sources).select("v", F.lit(0).alias("q"))
    found, rounds = _spread(first, steps, [], how)
    how.note(stage="reach", rounds=rounds)
    return _ended(found, a, steps)


def _ended(found: DataFrame, a: Automaton, steps: DataFrame) -> DataFrame:
    """Found rows in a final state; state 0 counts only where a step has led back to it."""
    keep = F.col("q").isin(sorted(a.finals - {0})) if a.finals - {0} else F.lit(False)
    out = found.where(keep)
    if 0 in a.finals and any(p == 0 for _, _, p in a.transitions):
        tag = [c for c in found.columns if c not in ("v", "q")]
        again = found.select(*tag, F.col("v").alias("u"), "q").join(steps.where("p = 0"), ["u", "q"]).select(*tag, "v", F.lit(0).alias("q"))
        out = out.union(again.distinct())
    return out.drop("q")


def _trimmed(g: LabeledGraph, a: Automaton, sources: DataFrame | None, targets: DataFrame | None, how: Evaluation) -> DataFrame:
    """Steps on walks from a source to a target: two linear searches."""
    steps = how.scratch.table(g.step_relation(a).select("u", "q", "v", "p"))
    ahead, n = _spread(_start(steps, sources).select("v", F.lit(0).alias("q")), steps, [], how)
    steps = how.scratch.table(steps.join(ahead.select(F.col("v").alias("u"), "q").distinct(), ["u", "q"], "left_semi").select("u", "q", "v", "p"))
    last = steps.where(F.col("p").isin(sorted(a.finals))).select("v", F.col("p").alias("q")).distinct()
    last = last if targets is None else last.join(targets, "v", "left_semi").select("v", "q")
    back = steps.select(F.col("v").alias("u"), F.col("p").alias("q"), F.col("u").alias("v"), F.col("q").alias("p"))
    behind, m = _spread(last, back, [], how)
    how.note(stage="trim", rounds=n + m)
    return how.scratch.table(steps.join(behind.select("v", F.col("q").alias("p")).distinct(), ["v", "p"], "left_semi").select("u", "q", "v", "p"))


def _capped(g: LabeledGraph, a: Automaton, sources: DataFrame | None, targets: DataFrame | None, how: Evaluation) -> DataFrame:
    """(s, v): backward lists of at most cap + 1 targets a node, then a search from the sources whose list is full.

    A source with fewer is complete.  If more sources are full than cap, cap is
    doubled: so it ends at no more than twice the root of the result's size,
    and no node ever holds more than cap + 1 rows.
    """
    steps = _trimmed(g, a, sources, targets, how)
    cap = 16 if how.cap == "auto" else int(how.cap)
    starts = how.scratch.table(_start(steps, sources))
    last = steps.where(F.col("p").isin(sorted(a.finals))).select("v", F.col("p").alias("q")).distinct()
    last = last if targets is None else last.join(targets, "v", "left_semi").select("v", "q")
    last = how.scratch.table(last)
    while True:
        held, rounds, touched = _lists(steps, last, cap, how)
        behind = steps.where("q = 0").select(F.col("u").alias("s"), F.col("v"), F.col("p").alias("q")).join(starts.withColumnRenamed("v", "s"), "s", "left_semi")
        mine = behind.join(held, ["v", "q"]).select("s", "t").distinct()
        sizes = how.scratch.table(mine.groupBy("s").agg(F.count(F.lit(1)).alias("n")))
        heavy = how.scratch.table(sizes.where(F.col("n") > cap).select(F.col("s").alias("v")))
        n_heavy = heavy.count()
        how.note(stage="capped", cap=cap, heavy=n_heavy, rounds=rounds, edges_touched=touched)
        if n_heavy <= cap:
            break
        cap *= 2
    light = mine.join(heavy.select(F.col("v").alias("s")), "s", "left_anti").select("s", F.col("t").alias("v"))
    if not n_heavy:
        return light
    found, _ = _spread(heavy.select(F.col("v").alias("s"), "v", F.lit(0).alias("q")), steps, ["s"], how)
    full = _ended(found, a, steps)
    full = full if targets is None else full.join(targets, "v", "left_semi").select("s", "v")
    return light.union(full.select("s", "v").distinct())


def _lists(steps: DataFrame, last: DataFrame, cap: int, how: Evaluation) -> tuple[DataFrame, int, int]:
    """(v, q, t): for each node, up to cap + 1 of the targets that it leads to; rounds; steps walked.

    A row that a node takes is handed to its predecessors once, in the next
    round; of those on offer a node takes the least.
    """
    spark, scratch = steps.sparkSession, how.scratch
    first = last.select("v", "q", F.col("v").alias("t"))
    paths, rounds, touched = [scratch.path(first)], 0, 0
    fresh = spark.read.schema(first.schema).parquet(paths[0])
    while True:
        held = spark.read.schema(first.schema).parquet(*paths)
        offered = steps.join(fresh.select("v", F.col("q").alias("p"), "t"), ["v", "p"]).select(F.col("u").alias("v"), "q", "t").distinct()
        offered = offered.join(held, ["v", "q", "t"], "left_anti")
        full = held.groupBy("v", "q").agg(F.count(F.lit(1)).alias("had"))
        ranked = offered.join(full, ["v", "q"], "left").withColumn("r", F.row_number().over(Window.partitionBy("v", "q").orderBy("t")))
        paths.append(scratch.path(ranked.where(F.col("r") <= F.lit(cap + 1) - F.coalesce("had", F.lit(0))).select("v", "q", "t")))
        fresh = spark.read.schema(first.schema).parquet(paths[-1])
        rounds += 1
        n = fresh.count()
        touched += n
        if not n or rounds >= how.max_rounds:
            return spark.read.schema(first.schema).parquet(*paths), rounds, touched


# ---- baselines for one expression


def base_all_sources(g: LabeledGraph, e: PathExpr, how: Evaluation | None = None) -> DataFrame:
    """(x, y) by a search from every vertex at once, in rounds: no cap, no trimming."""
    how = how or Evaluation(Scratch(g.edges.sparkSession, "base"))
    a = to_automaton(e)
    steps = how.scratch.table(g.step_relation(a).select("u", "q", "v", "p"))
    first = _start(steps, None).select(F.col("v").alias("s"), "v", F.lit(0).alias("q"))
    found, rounds = _spread(first, steps, ["s"], how)
    how.note(stage="all_sources", rounds=rounds)
    out = _ended(found, a, steps).select("s", "v")
    if nullable(e):
        out = out.union(g.vertices().select(F.col("v").alias("s"), "v"))
    return out.select(F.col("s").alias("x"), F.col("v").alias("y")).distinct()


def base_doubling(g: LabeledGraph, e: PathExpr, how: Evaluation | None = None) -> DataFrame:
    """(x, y) by squaring the closure of all steps: as many rounds as the logarithm of the longest walk."""
    how = how or Evaluation(Scratch(g.edges.sparkSession, "base"))
    a = to_automaton(e)
    now = how.scratch.table(g.step_relation(a).select("u", "q", "v", "p").distinct())
    size = now.count()
    while True:
        next_ = now.select("u", "q", F.col("v").alias("mv"), F.col("p").alias("mp")).join(now.select(F.col("u").alias("mv"), F.col("q").alias("mp"), "v", "p"), ["mv", "mp"]).select("u", "q", "v", "p")
        now = how.scratch.table(now.union(next_).distinct())
        if (n := now.count()) == size:
            break
        size = n
    keep = F.col("p").isin(sorted(a.finals)) if a.finals else F.lit(False)
    out = now.where((F.col("q") == 0) & keep).select(F.col("u").alias("s"), "v")
    if nullable(e):
        out = out.union(g.vertices().select(F.col("v").alias("s"), "v"))
    return out.select(F.col("s").alias("x"), F.col("v").alias("y")).distinct()
