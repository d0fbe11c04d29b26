"""Quality classifier: a factorisation machine over hashed words, structure and metadata."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.llm import kernel
from regpath.llm.common import digest, table

BUCKETS = 1 << 14
RANK = 6
#: Fitted on at most so many labelled rows, those of the least hash.
FIT_ROWS = 4_000
#: As many mini-batches at every size: small samples are gone through more often.
STEPS, BATCH, RATE, PENALTY = 800, 128, 0.05, 3e-3
GOOD = 0.7
STATISTICS = ("log_words", "word_length", "distinct", "upper", "marks", "symbols", "digits", "log_lines", "line_words", "non_ascii", "log_chars", "has_chars")


@dataclass(frozen=True)
class Machine:
    """Weights and factors; the last len(STATISTICS) features are the statistics, standardised."""

    bias: float
    weight: np.ndarray
    factor: np.ndarray
    mean: np.ndarray
    spread: np.ndarray


def features(texts: pa.Array, n_chars: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct word buckets in order, their offsets, and a row of statistics for each text."""
    data, off = kernel.bytes_of(texts)
    if len(off) == 2 and len(data) > kernel.SEGMENT:
        buckets, to, n, distinct = _of_long(data, off)
    else:
        words, at = kernel.word_hashes(data, off)
        buckets, to = kernel.as_sets(words % np.uint64(BUCKETS), at)
        n, distinct = np.diff(at), np.diff(kernel.as_sets(words, at)[1])
    size = np.maximum(1, np.diff(off))
    share = lambda kind: kernel.byte_counts(data, off, kind) / size
    lines = kernel.byte_counts(data, off, NEW_LINE) + 1.0
    chars = np.nan_to_num(n_chars, nan=0.0)
    stats = [np.log1p(n), size / np.maximum(1, n), distinct / np.maximum(1, n), share(UPPER), share(PUNCTUATION), share(SYMBOL), share(DIGIT), np.log1p(lines), np.log1p(n / lines), share(HIGH), np.log1p(np.maximum(0, chars)), ~np.isnan(n_chars)]
    return buckets.astype(np.int64), to, np.array(stats, dtype=np.float64).T.reshape(len(texts), len(STATISTICS))


def _of_long(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Word buckets, their offsets, and numbers of words and distinct words of one text, of which only distinct words are held."""
    seen, n = [np.zeros(0, dtype=np.uint64)], 0
    for words, _ in kernel.word_segments(data, off):
        n += len(words)
        seen.append(np.unique(words))
        if len(seen) > 16:
            seen = [np.unique(np.concatenate(seen))]
    distinct = np.unique(np.concatenate(seen))
    buckets = np.unique(distinct % np.uint64(BUCKETS))
    return buckets, np.array([0, len(buckets)]), np.array([n]), np.array([len(distinct)])


def _kind(chars: bytes) -> np.ndarray:
    out = np.zeros(256, dtype=bool)
    out[list(chars)] = True
    return out


UPPER, DIGIT, NEW_LINE = _kind(bytes(range(65, 91))), _kind(b"0123456789"), _kind(b"\n")
PUNCTUATION, SYMBOL, HIGH = _kind(b".,;:!?'\"()-"), _kind(b"#$%&*|@^~<>{}[]\\/_=+"), _kind(bytes(range(128, 256)))


def scores(m: Machine, buckets: np.ndarray, off: np.ndarray, stats: np.ndarray) -> np.ndarray:
    """Chance of label 1 of each row, in time linear in its features: half of (sum squared less sum of squares) a factor."""
    x = 1 / np.sqrt(np.maximum(1, np.diff(off)))
    z = np.clip((stats - m.mean) / m.spread, -4, 4)
    out = m.bias + kernel.sums(m.weight[:BUCKETS][buckets], off) * x + z @ m.weight[BUCKETS:]
    for f in range(m.factor.shape[1]):
        v, s = m.factor[:BUCKETS, f][buckets], m.factor[BUCKETS:, f]
        both = kernel.sums(v, off) * x + z @ s
        out += 0.5 * (both**2 - kernel.sums(v * v, off) * x**2 - (z**2) @ (s**2))
    return 1 / (1 + np.exp(-np.clip(out, -30, 30)))


def fit(rows: list[tuple[list[int], list[float], int]]) -> Machine:
    """Logistic loss by mini-batches with per-weight step sizes; the same rows give the same machine."""
    rng, size = np.random.Generator(np.random.PCG64(7)), BUCKETS + len(STATISTICS)
    w, v, bias = np.zeros(size), rng.normal(0, 0.02, (size, RANK)), 0.0
    if not rows:
        return Machine(0.0, w, v * 0, np.zeros(len(STATISTICS)), np.ones(len(STATISTICS)))
    stats, label = np.array([r[1] for r in rows], dtype=np.float64), np.array([r[2] for r in rows], dtype=np.float64)
    mean, spread = stats.mean(axis=0), np.maximum(stats.std(axis=0), 1e-6)
    z = np.clip((stats - mean) / spread, -4, 4)
    words = [np.array(r[0], dtype=np.int64) for r in rows]
    bias = float(np.log((label.sum() + 1) / (len(label) - label.sum() + 1)))
    seen_w, seen_v = np.full(size, 1e-8), np.full((size, RANK), 1e-8)
    extra = np.arange(BUCKETS, size)
    for _ in range(-(-STEPS * BATCH // max(BATCH, len(rows)))):
        order = rng.permutation(len(rows))
        for a in range(0, len(rows), BATCH):
            own = order[a : a + BATCH]
            n = np.array([len(words[i]) for i in own])
            idx = np.concatenate([np.concatenate([words[i], extra]) for i in own])
            val = np.concatenate([np.concatenate([np.full(len(words[i]), 1 / np.sqrt(max(1, len(words[i])))), z[i]]) for i in own])
            row = np.repeat(np.arange(len(own)), n + len(extra))
            start = np.concatenate([[0], np.cumsum(n + len(extra))[:-1]])
            both = np.add.reduceat(v[idx] * val[:, None], start, axis=0)
            square = np.add.reduceat((v[idx] * val[:, None]) ** 2, start, axis=0)
            out = bias + np.add.reduceat(w[idx] * val, start) + 0.5 * (both**2 - square).sum(axis=1)
            slope = (1 / (1 + np.exp(-np.clip(out, -30, 30))) - label[own]) / len(own)
            bias -= 0.5 * slope.sum()
            used, place = np.unique(idx, return_inverse=True)
            gw = np.bincount(place, slope[row] * val) + PENALTY * w[used]
            inner = slope[row, None] * val[:, None] * (both[row] - v[idx] * val[:, None])
            gv = np.array([np.bincount(place, inner[:, f]) for f in range(RANK)]).T + PENALTY * v[used]
            seen_w[used] += gw**2
            seen_v[used] += gv**2
            w[used] -= RATE * 4 * gw / np.sqrt(seen_w[used])
            v[used] -= RATE * gv / np.sqrt(seen_v[used])
    return Machine(bias, w, v, mean, spread)


def _featured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at, to in kernel.portions(batch.column("text")):
            buckets, off, stats = features(batch.column("text").slice(at, to - at), _numbers(batch.column("n_chars").slice(at, to - at)))
            lists = pa.ListArray.from_arrays(pa.array(off.astype(np.int32)), pa.array(buckets.astype(np.int32)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(at, to - at), lists, pa.array(stats.tolist(), pa.list_(pa.float64()))], names=["doc_id", "buckets", "stats"])


def _numbers(column: pa.Array) -> np.ndarray:
    return column.cast(pa.float64()).to_numpy(zero_copy_only=False)


def _scored(machine: Broadcast[Machine]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, to in kernel.portions(batch.column("text")):
                text = batch.column("text").slice(at, to - at)
                out = scores(machine.value, *features(text, _numbers(batch.column("n_chars").slice(at, to - at))))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(at, to - at), pa.array(out)], names=["doc_id", "score"])

    return run


def held_out(key: Column) -> Column:
    """Rows never learned from: crc32 of the key as text leaves 2 when divided by 4."""
    return F.coalesce(F.pmod(F.crc32(key.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS) -> Machine:
    """Fits on a bounded sample of the labelled rows that are not held out, fixed by their keys."""
    known = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("quality").alias("quality"))
    sample = known.orderBy(digest("quality", F.col("doc_id")), "doc_id").limit(fit_rows)
    text = docs.select("doc_id", "text", "n_chars").join(F.broadcast(sample.select("doc_id")), "doc_id", "left_semi")
    rows = {r["doc_id"]: (r["buckets"], r["stats"]) for r in text.mapInArrow(_featured, "doc_id long, buckets array<int>, stats array<double>").collect()}
    label = {r["doc_id"]: r["quality"] for r in sample.collect()}
    return fit([(*rows[d], label[d]) for d in sorted(rows)])


def classify(docs: DataFrame, machine: Machine) -> DataFrame:
    """(doc_id, held_out, score, predicted) of each row, from its whole text and n_chars alone.

    Null and empty texts are scored by their statistics; a null n_chars is a
    feature of its own; null keys are not held out.
    """
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("n_chars").cast("double").alias("n_chars"))
    out = own.mapInArrow(_scored(docs.sparkSession.sparkContext.broadcast(machine)), "doc_id long, score double")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= GOOD).cast("int").alias("predicted"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The quality of every document."""
    docs = table(spark, sf_dir, "documents")
    return classify(docs, train(docs, table(spark, sf_dir, "labels")))
