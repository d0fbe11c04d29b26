"""MinHash near-dedup: fast similarity sketches, banding, and exact verification."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.llm import kernel
from regpath.llm.common import small, table
from regpath.operators.components import connected_components
from regpath.operators.scratch import Scratch

#: 42 bands of 6 coordinates: at a similarity of 0.8, all bands of a pair differ with a chance of 3 in a million.
BAND_ROWS, BANDS = 6, 42
#: A group of more sets, or of more shingles in all, is compared in blocks of at most so many, two blocks a task.
BLOCK_SETS, BLOCK_SHINGLES = 512, 1_500_000
#: Elements in one batch of sets on their way to the tasks.
DEALT_AT_ONCE = 500_000
#: Columns of the incidence matrix held at once.
COLUMNS = 16_384


def _sets(texts: pa.Array, k: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, set elements, offsets) for portions of the texts."""
    for at, to in kernel.portions(texts):
        words, off = kernel.word_hashes(*kernel.bytes_of(texts.slice(at, to - at)))
        yield at, *kernel.as_sets(*kernel.shingles(words, off, k))


def _sketched(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, values, off in _sets(batch.column("text"), k):
                n, some = len(off) - 1, np.diff(off) > 0
                keys = kernel.bands(kernel.sketches(values, off, BANDS * BAND_ROWS), BAND_ROWS)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(some * BANDS)]).astype(np.int32)), pa.array(keys[some].reshape(-1).view(np.int64)))
                digest = [kernel.sums(kernel.mixed(values + kernel.PLACE_FACTOR[60 - i]), off).view(np.int64) for i in range(2)]
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(at, n), pa.array(np.diff(off)), *map(pa.array, digest), lists], names=["doc_id", "n_shingles", "d1", "d2", "bands"]
                )

    return run


def _dealt(k: int):
    """A copy of each document's set for each block pair that compares it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            tasks, ids = batch.column("tasks"), batch.column("doc_id")
            start, inner = tasks.offsets.to_numpy(), tasks.values
            hub, i, j, own = (inner.field(x).to_numpy() for x in ("hub", "i", "j", "own"))
            for at, values, off in _sets(batch.column("text"), k):
                here = start[at : at + len(off)]
                row, length = np.repeat(np.arange(len(off) - 1), np.diff(here)), np.diff(off)
                ends = np.cumsum(length[row])
                a = 0
                while a < len(row):
                    b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + DEALT_AT_ONCE, "right")))
                    many = length[row[a:b]]
                    to = np.concatenate([[0], np.cumsum(many)])
                    elements = values[np.arange(to[-1]) - np.repeat(to[:-1], many) + np.repeat(off[row[a:b]], many)]
                    c, d = here[0] + a, here[0] + b
                    columns = [*(pa.array(x[c:d]) for x in (hub, i, j, own)), ids.take(pa.array(row[a:b] + at)), pa.ListArray.from_arrays(pa.array(to.astype(np.int32)), pa.array(elements.view(np.int64)))]
                    yield pa.RecordBatch.from_arrays(columns, names=["hub", "i", "j", "own", "doc_id", "elements"])
                    a = b

    return run


def common_counts(a: list[np.ndarray], b: list[np.ndarray] | None = None) -> np.ndarray:
    """How many elements each set of a has in common with each of b (of a, without b)."""
    both = a if b is None else a + b
    rows = np.repeat(np.arange(len(both)), [len(x) for x in both])
    _, column, often = np.unique(np.concatenate(both), return_inverse=True, return_counts=True)
    keep = often[column] > 1
    renamed = np.cumsum(often > 1) - 1
    rows, column = rows[keep], renamed[column[keep]]
    order = np.argsort(column, kind="stable")
    rows, column = rows[order], column[order]
    out = np.zeros((len(a), len(both) if b is None else len(b)), dtype=np.float64)
    width = int(column[-1]) + 1 if len(column) else 0
    for at in range(0, width, COLUMNS):
        lo, hi = np.searchsorted(column, [at, at + COLUMNS])
        part = np.zeros((len(both), min(COLUMNS, width - at)), dtype=np.float32)
        part[rows[lo:hi], column[lo:hi] - at] = 1
        out += part @ part.T if b is None else part[: len(a)] @ part[len(a) :].T
    return out.astype(np.int64)


def forest(similar: np.ndarray, ids: np.ndarray) -> list[tuple[int, int]]:
    """Links that connect what the symmetric matrix connects, one less than nodes in each component."""
    out, left = [], np.ones(len(ids), dtype=bool)
    for root in range(len(ids)):
        if not left[root]:
            continue
        left[root], stack = False, [root]
        while stack:
            x = stack.pop()
            for y in np.flatnonzero(similar[x] & left):
                left[y] = False
                stack.append(y)
                out.append((int(ids[x]), int(ids[y])))
    return out


def _pairwise(sets: list[np.ndarray], percent: int) -> np.ndarray:
    """For few sets: the matrix of links, without pairs that other links connect already."""
    n = len(sets)
    similar, root = np.zeros((n, n), dtype=bool), list(range(n))
    for x in range(n):
        for y in range(x + 1, n):
            a, b = (sets[x], sets[y]) if len(sets[x]) <= len(sets[y]) else (sets[y], sets[x])
            if root[x] == root[y] or 100 * len(a) < percent * len(b):
                continue
            place = np.minimum(np.searchsorted(b, a), len(b) - 1)
            both = int(np.count_nonzero(b[place] == a))
            if 100 * both >= percent * (len(a) + len(b) - both):
                similar[x, y] = similar[y, x] = True
                old, new = root[y], root[x]
                root = [new if r == old else r for r in root]
    return similar


def links_within(ids: np.ndarray, own: np.ndarray, i: int, j: int, sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Links among the sets of one block (i = j) or between those of two."""
    if len(ids) <= 24 and i == j:
        return forest(_pairwise(sets, percent), ids)
    size = np.array([len(x) for x in sets])
    if i == j:
        both = common_counts(sets)
        similar = 100 * both >= percent * (size[:, None] + size[None, :] - both)
    else:
        similar = np.zeros((len(ids), len(ids)), dtype=bool)
        left, right = np.flatnonzero(own == i), np.flatnonzero(own == j)
        if not len(left) or not len(right):
            return []
        both = common_counts([sets[x] for x in left], [sets[x] for x in right])
        part = 100 * both >= percent * (size[left][:, None] + size[right][None, :] - both)
        similar[np.ix_(left, right)], similar[np.ix_(right, left)] = part, part.T
    np.fill_diagonal(similar, False)
    return forest(similar, ids)


def _verified(percent: int):
    """Links of each (hub, i, j), whose rows stand next to each other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held, out = None, [], []

        def settle():
            if len(held) > 1:
                ids, own, sets = zip(*held, strict=True)
                out.extend(links_within(np.array(ids), np.array(own), now[1], now[2], list(sets), percent))
            held.clear()

        for batch in batches:
            hub, i, j, own, ids = (batch.column(x).to_numpy() for x in ("hub", "i", "j", "own", "doc_id"))
            lists = batch.column("elements")
            start, values = lists.offsets.to_numpy(), lists.values.to_numpy().view(np.uint64)
            for r in range(len(hub)):
                if (key := (hub[r], i[r], j[r])) != now:
                    settle()
                    now = key
                held.append((ids[r], own[r], values[start[r] : start[r + 1]].copy()))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([x[c] for x in out], pa.int64()) for c in (0, 1)], names=["a", "b"])
                out.clear()
        settle()
        if out:
            yield pa.RecordBatch.from_arrays([pa.array([x[c] for x in out], pa.int64()) for c in (0, 1)], names=["a", "b"])

    return run


def near_duplicates(docs: DataFrame, k: int = 2, percent: int = 80, key: str = "doc_id", text: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """(key, n_shingles, component_id, kept) for each row of docs.

    A set is the distinct runs of k words (fewer words: the whole sequence); words are parted by ASCII blanks, A-Z
    count as a-z.  Sets with percent/100 of their union in common are linked; component_id is the least key that links
    reach.  Null and empty texts, and rows without a key, link with nothing; the latter keep a null
    component_id.  Rows with equal keys are one document, which links as each of its texts does.

    Equal sets are first put in classes, of which only the least key goes on.
    Sets that share a band are compared in full.  Each shared band has a
    hub, its least key; a set is sent once to each of its hubs, where all that
    came are compared with each other, so every pair that shares a band meets.
    Large groups are compared in blocks, two blocks a task, and give a
    spanning forest of their links, never all pairs.  Joins are merge joins at
    every size: what they broadcast would grow with the documents.
    """
    scratch = scratch or Scratch(docs.sparkSession, "neardup")
    own = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"))
    sketched = scratch.table(own.mapInArrow(_sketched(k), "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>"))
    ids = sketched.where("n_shingles > 0 and doc_id is not null").select("doc_id", "n_shingles", "d1", "d2")
    # written, so that the join behind has two plain shuffles, and Spark can split a class of a third of all rows
    classes = scratch.table(ids.groupBy("n_shingles", "d1", "d2").agg(F.min("doc_id").alias("rep")))
    members = scratch.table(ids.join(classes.hint("merge"), ["n_shingles", "d1", "d2"]).select("doc_id", "n_shingles", "rep"))

    leaders = members.where("doc_id = rep").select("doc_id").distinct()
    keyed = sketched.join(leaders.hint("merge"), "doc_id", "left_semi").select(F.col("doc_id").alias("rep"), F.explode("bands").alias("band"))
    keyed = scratch.table(keyed)
    hubs = scratch.table(keyed.groupBy("band").agg(F.min("rep").alias("hub"), F.max("rep").alias("other")).where("hub < other").select("band", "hub"))
    met = keyed.join(hubs.hint("merge"), "band").select("hub", "rep").distinct()
    sent = scratch.table(met.join(members.groupBy("rep").agg(F.max("n_shingles").alias("n")).hint("merge"), "rep"))
    groups = sent.groupBy("hub").agg(F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_SETS), F.ceil(F.sum("n") / BLOCK_SHINGLES)).cast("int").alias("blocks"))
    groups = scratch.table(groups)
    placed = sent.join(groups, "hub").withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    placed = placed.withColumn("j", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    task = F.struct("hub", F.least("own", "j").alias("i"), F.greatest("own", "j").alias("j"), "own")
    # a document has at most as many hubs as bands, and goes to each block of a hub once
    tasks = placed.groupBy(F.col("rep").alias("doc_id")).agg(F.collect_list(task).alias("tasks"))
    sets = own.join(tasks.hint("merge"), "doc_id").mapInArrow(_dealt(k), "hub long, i int, j int, own int, doc_id long, elements array<long>")
    found = sets.repartition("hub", "i", "j").sortWithinPartitions("hub", "i", "j").mapInArrow(_verified(percent), "a long, b long")
    twice = members.groupBy("doc_id").agg(F.min("rep").alias("least"), F.max("rep").alias("most")).where("least < most")
    again = members.join(twice, "doc_id", "left_semi").select("doc_id", "rep")
    reached = connected_components(found.union(again), scratch)
    joined = members.join(reached.hint("merge"), members["rep"] == reached["node"], "left")
    done = joined.select("doc_id", "n_shingles", F.coalesce("component", "rep").alias("component_id"))
    alone = sketched.where("n_shingles = 0 or doc_id is null").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    every = done.union(alone)
    return every.select(F.col("doc_id").alias(key), "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def keep_one(docs: DataFrame, scratch: Scratch | None = None, **how) -> DataFrame:
    """One row of docs for each group of near-duplicates: of its least doc_id, and of these of the least text hash.

    Rows of equal doc_id, or of none, are documents of their own unless their texts are near-duplicates too.
    Texts without a word link with nothing: of such rows only those of equal doc_id and text count as one.
    """
    scratch = scratch or Scratch(docs.sparkSession, "neardup")
    names = docs.columns
    if small(docs.groupBy("doc_id").count().where("count > 1 or doc_id is null"), 0):
        dropped = near_duplicates(docs, scratch=scratch, **how).where("not kept").select("doc_id")
        return docs.join(scratch.table(dropped).hint("merge"), "doc_id", "left_anti").select(*[F.col(f"`{c}`") for c in names])
    mark = F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("none")), F.coalesce("text", F.lit("")))
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), mark.alias("mark"), F.col("doc_id").alias("key"), "text")
    found = scratch.table(near_duplicates(own, key="mark", scratch=scratch, **how).select(F.col("mark").alias("of"), F.col("component_id").alias("group")).distinct())
    ids = scratch.table(own.select("mark", "key").distinct())
    first = ids.join(found.hint("merge"), F.col("mark") == F.col("of")).groupBy("group").agg(F.min(F.struct(F.col("key").isNull().alias("without"), "key", "mark")).alias("x")).select(F.col("x.mark").alias("kept"))
    left = own.join(first.hint("merge"), F.col("mark") == F.col("kept"), "left_semi")
    one = left.groupBy("mark").agg(F.min_by("row", F.to_json("row")).alias("row"))
    return one.select(*[F.col("row")[c].alias(c) for c in names])


def op9_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicates of two-word shingles among all documents."""
    return near_duplicates(table(spark, sf_dir, "documents"))
