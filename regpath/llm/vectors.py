"""Embedding near-dedup: cross-polytope hashing after fast Hadamard rotations, and verified pairs."""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.llm import kernel
from regpath.llm.common import table
from regpath.llm.neardup import forest
from regpath.operators.components import connected_components
from regpath.operators.scratch import Scratch

COSINE = 0.95
#: Vectors of a group are compared in blocks of at most so many, two blocks a task.
BLOCK = 1_024
#: Numbers of a batch that are rotated at once.
AT_ONCE = 1 << 18


def plan(vectors: int, dim: int) -> tuple[int, int]:
    """(hashes joined to a code, tables): codes outnumber the vectors, and more tables make up for longer codes.

    With probes = hashes + 1, a pair of cosine 0.95 in 64 dimensions shares a
    code of one of the tables but for about 3 in 100 000.
    """
    depth = max(3, math.ceil(math.log(4 * max(2, vectors)) / math.log(2 * max(2, 1 << max(1, (dim - 1).bit_length())))))
    return depth, 3 * depth - 1


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast Walsh-Hadamard transform of each row; the row length is a power of two."""
    h = 1
    while h < x.shape[1]:
        y = x.reshape(len(x), -1, 2, h)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], axis=2).reshape(len(x), -1)
        h *= 2
    return x


def codes(x: np.ndarray, depth: int, tables: int) -> np.ndarray:
    """Codes of each row: for each table its own, and those reached by the `depth` cheapest changes of its hashes.

    A hash is the greatest coordinate, with its sign, after three rounds of
    random signs and Hadamard transforms; a change takes the second or third
    greatest instead, and costs the square of what is lost.
    """
    n, dim = x.shape
    size = max(4, 1 << max(0, (dim - 1).bit_length()))
    padded = np.zeros((n, size))
    padded[:, :dim] = x / np.linalg.norm(x, axis=1, keepdims=True)
    swaps = [c for c in itertools.product(range(3), repeat=depth) if sum(c) <= 2]
    signs = np.random.Generator(np.random.PCG64([size, 5])).choice(np.array([-1.0, 1.0]), size=(tables, depth, 3, size))
    out = np.empty((n, tables, depth + 1), dtype=np.uint64)
    for t in range(tables):
        tops, losses = [], []
        for s in signs[t]:
            y = padded
            for sign in s:
                y = hadamard(y * sign)
            top = np.argsort(-np.abs(y), axis=1, kind="stable")[:, :3]
            value = np.take_along_axis(y, top, 1)
            tops.append((2 * top + (value < 0)).astype(np.uint64))
            losses.append(((np.abs(value[:, :1]) - np.abs(value)) / np.linalg.norm(y, axis=1, keepdims=True)) ** 2)
        lost = np.array([sum(losses[i][:, c] for i, c in enumerate(s)) for s in swaps])
        all_codes = np.full((len(swaps), n), ((t + 1) * int(kernel.BASE) + dim) % (1 << 64), dtype=np.uint64)
        for i in range(depth):
            all_codes = kernel.mixed(all_codes + np.array([tops[i][:, s[i]] for s in swaps]) * kernel.PLACE_FACTOR[i])
        best = np.argsort(lost, axis=0, kind="stable")[: depth + 1]
        out[:, t, :] = np.take_along_axis(all_codes, best, 0).T
    return out.reshape(n, -1)


def _rows(column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row numbers, matrix) of the usable vectors of a batch, by length and in bounded parts."""
    start, values = column.offsets.to_numpy(), column.values
    flat = values.cast(pa.float64()).fill_null(math.nan).to_numpy(zero_copy_only=False)
    length = np.where(column.is_valid().to_numpy(zero_copy_only=False), np.diff(start), 0)
    for dim in np.unique(length[length > 0]):
        rows, step = np.flatnonzero(length == dim), max(1, AT_ONCE // int(dim))
        for a in range(0, len(rows), step):
            own = rows[a : a + step]
            x = flat[start[own][:, None] + np.arange(dim)]
            with np.errstate(over="ignore", invalid="ignore"):
                good = np.isfinite(x).all(axis=1) & (np.abs(x).max(axis=1) > 0)
            if good.any():
                yield own[good], _scaled(x[good])


def _scaled(x: np.ndarray) -> np.ndarray:
    """Rows divided by a power of two near their greatest number: no square overflows or vanishes, no digit is lost."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, keepdims=True))[1])


def _coded(depth: int, tables: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, x in _rows(batch.column("embedding")):
                found = codes(x, depth, tables)
                raw = kernel.mixed((x + 0.0).view(np.uint64) ^ kernel.mixed(np.arange(1, x.shape[1] + 1, dtype=np.uint64)))
                digest = [kernel.mixed(raw + kernel.PLACE_FACTOR[50 - i]).sum(axis=1, dtype=np.uint64).view(np.int64) for i in range(2)]
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * found.shape[1]), pa.array(found.reshape(-1).view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column("vec_id").take(pa.array(rows)), *map(pa.array, digest), lists], names=["vec_id", "d1", "d2", "codes"])

    return run


def _first_met(hubs: list[np.ndarray], hub: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Whether each pair of rows has no smaller hub in common, so that it is counted once."""
    width = max(len(h) for h in hubs)
    padded = np.full((len(hubs), width), hub, dtype=np.int64)
    for r, h in enumerate(hubs):
        padded[r, : len(h)] = h
    least = padded.min(axis=1)
    out = (least[x] >= hub) | (least[y] >= hub)
    for a in range(0, len(x), 4_096):
        part = np.flatnonzero(~out[a : a + 4_096]) + a
        p, q = padded[x[part]], padded[y[part]]
        out[part] = ~((p[:, :, None] == q[:, None, :]) & (p[:, :, None] < hub)).any(axis=(1, 2))
    return out


def _verified(cosine: float):
    """For each (hub, i, j): links counted by vector (b null), and a spanning forest of them (n null)."""

    def settle(key, held, out):
        ids, own, weight, vectors, hubs = zip(*held, strict=True)
        ids, own, weight = np.array(ids), np.array(own), np.array(weight)
        length = np.array([len(v) for v in vectors])
        for dim in np.unique(length):
            rows = np.flatnonzero(length == dim)
            x = _scaled(np.array([vectors[r] for r in rows], dtype=np.float64))
            norm = np.sqrt((x * x).sum(axis=1))
            left, right = (rows, rows) if key[1] == key[2] else (rows[own[rows] == key[1]], rows[own[rows] == key[2]])
            at = {r: i for i, r in enumerate(rows)}
            li, ri = np.array([at[r] for r in left], dtype=np.int64), np.array([at[r] for r in right], dtype=np.int64)
            if not len(li) or not len(ri):
                continue
            near = (x[li] @ x[ri].T) / (norm[li][:, None] * norm[ri][None, :]) >= cosine
            if key[1] == key[2]:
                near = np.triu(near, 1)
            a, b = np.nonzero(near)
            a, b = li[a], ri[b]
            similar = np.zeros((len(rows), len(rows)), dtype=bool)
            similar[a, b] = similar[b, a] = True
            out.extend((p, q, None) for p, q in forest(similar, ids[rows]))
            once = _first_met([hubs[r] for r in rows], key[0], a, b)
            many = np.zeros(len(rows), dtype=np.int64)
            np.add.at(many, a[once], weight[rows][b[once]])
            np.add.at(many, b[once], weight[rows][a[once]])
            out.extend((int(ids[rows[r]]), None, int(many[r])) for r in np.flatnonzero(many))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held, out = None, [], []
        for batch in itertools.chain(batches, [None]):
            if batch is None:
                rows = []
            else:
                rows = zip(*(batch.column(c).to_numpy() for c in ("hub", "i", "j", "own", "vec_id", "weight")), *(_lists(batch.column(c)) for c in ("embedding", "hubs")), strict=True)
            for hub, i, j, own, vec, weight, x, hubs in rows:
                if (hub, i, j) != now:
                    if len(held) > 1:
                        settle(now, held, out)
                    now, held = (hub, i, j), []
                if not any(h[0] == vec and np.array_equal(h[3], x) for h in itertools.takewhile(lambda h, v=vec: h[0] == v, reversed(held))):
                    held.append((vec, own, weight, x.copy(), hubs.copy()))
            if batch is None and len(held) > 1:
                settle(now, held, out)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([x[c] for x in out], pa.int64()) for c in range(3)], names=["a", "b", "n"])
                out.clear()

    return run


def _lists(column: pa.Array) -> Iterator[np.ndarray]:
    start, values = column.offsets.to_numpy(), column.values.to_numpy()
    for a, b in itertools.pairwise(start):
        yield values[a:b]


def linked(vectors: DataFrame, cosine: float = COSINE, key: str = "vec_id", embedding: str = "embedding", scratch: Scratch | None = None) -> DataFrame:
    """(key, n_links, component_id, kept): one row for each vector.

    Vectors of equal length and of a cosine of at least `cosine` are linked; null
    and zero vectors, and those with null or non-finite components, link with
    nothing.  Equal vectors are one class, of which the least key is hashed;
    its other members count as its links.  Vectors that share a code meet at
    the least key of each shared code, where all that came are compared in
    double precision, large groups in blocks, two blocks a task.  A pair counts
    at the least key at which it meets.  Links go on as a spanning forest,
    never as all pairs.  Repeated rows are one vector; rows of one key and
    different vectors link as each does; rows without a key are left out.
    """
    scratch = scratch or Scratch(vectors.sparkSession, "vectors")
    own = vectors.where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("vec_id"), F.col(embedding).alias("embedding"))
    size = own.agg(F.count(F.lit(1)), F.max(F.size("embedding"))).first()
    depth, tables = plan(size[0], max(1, size[1] or 1))
    coded = scratch.table(own.mapInArrow(_coded(depth, tables), "vec_id long, d1 long, d2 long, codes array<long>"))
    ids = coded.select("vec_id", "d1", "d2").distinct()
    # tables that are joined with what they were counted from are written: two plain shuffles can be split where a key is frequent
    classes = scratch.table(ids.groupBy("d1", "d2").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("weight")))
    members = scratch.table(ids.join(classes, ["d1", "d2"]).select("vec_id", "rep", "weight"))
    leaders = members.where("vec_id = rep").select("vec_id", "weight").distinct()
    keyed = scratch.table(coded.join(leaders, "vec_id").select(F.col("vec_id").alias("rep"), "weight", F.explode("codes").alias("code")))
    hubs = scratch.table(keyed.groupBy("code").agg(F.min("rep").alias("hub"), F.max("rep").alias("other")).where("hub < other").select("code", "hub"))
    sent = scratch.table(keyed.join(hubs, "code").select("hub", "rep", "weight").distinct())
    groups = scratch.table(sent.groupBy("hub").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks")))
    placed = sent.join(groups, "hub").withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    # a vector has at most as many hubs as codes
    hubs_of = placed.groupBy("rep").agg(F.collect_list(F.struct("hub", "own", "blocks")).alias("at"), F.max("weight").alias("weight"))
    distinct = own.join(hubs_of, own["vec_id"] == hubs_of["rep"]).select("vec_id", "weight", "embedding", F.sort_array(F.transform("at", lambda h: h["hub"])).alias("hubs"), F.explode("at").alias("h"))
    tasks = distinct.select("vec_id", "weight", "embedding", "hubs", F.col("h.hub").alias("hub"), F.col("h.own").alias("own"), F.explode(F.sequence(F.lit(0), F.col("h.blocks") - 1)).alias("other"))
    tasks = tasks.select("hub", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "vec_id", "weight", "embedding", "hubs")
    found = scratch.table(tasks.repartition("hub", "i", "j").sortWithinPartitions("hub", "i", "j", "vec_id").mapInArrow(_verified(cosine), "a long, b long, n long"))
    counts = found.where("n is not null").groupBy(F.col("a").alias("rep")).agg(F.sum("n").alias("links"))
    twice = members.groupBy("vec_id").agg(F.min("rep").alias("least"), F.max("rep").alias("most")).where("least < most")
    again = members.join(twice, "vec_id", "left_semi").select("vec_id", "rep")
    reached = connected_components(found.where("b is not null").select("a", "b").union(again), scratch)
    joined = members.join(counts, "rep", "left").join(reached, members["rep"] == reached["node"], "left")
    done = joined.select("vec_id", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    every = own.select("vec_id").distinct().join(done.groupBy("vec_id").agg(F.max("n_links").alias("n_links"), F.min("component_id").alias("component_id")), "vec_id", "left")
    out = every.select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.select(F.col("vec_id").alias(key), "n_links", "component_id", (F.col("vec_id") == F.col("component_id")).alias("kept"))


def op3_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All embeddings, linked from a cosine of 0.95."""
    return linked(table(spark, sf_dir, "embeddings"))
