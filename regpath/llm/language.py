"""Language identification: text likelihoods fused with declared languages, address suffixes and host priors."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from regpath.llm import kernel
from regpath.llm.common import if_small, table
from regpath.llm.lines import host_of, lines_of
from regpath.operators.scratch import Scratch

CODES = 1 << 15
#: The text model is fitted on about so many rows with a declared language: an equal part for each language, its rows of the least hash.
FIT_ROWS = 3_000
#: A language needs so many rows of all, and has up to so many in the sample at least.
FIT_LEAST, FIT_EACH = 5, 200
#: Trigrams beyond so many add no more certainty: they are far from independent.
EVIDENCE = 40.0
DECLARED_RIGHT, SUFFIX_RIGHT, UNKNOWN = 0.9, 0.8, 1e-3
#: Rows of the parent that a host's, or a suffix's, own counts are smoothed with.
HOST_WEIGHT = 20.0
ACCEPTED = 0.5
HOSTS_BROADCAST = 100_000
#: Country suffixes and the language they hint at.
SUFFIXES = {"de": "de", "at": "de", "fr": "fr", "es": "es", "mx": "es", "ar": "es", "uk": "en", "us": "en", "au": "en", "ie": "en", "it": "it", "pt": "pt", "br": "pt", "nl": "nl", "pl": "pl", "ru": "ru"}


@dataclass(frozen=True)
class TextModel:
    """Log-probabilities of hashed byte trigrams by language; the last row is any text at all."""

    languages: tuple[str, ...]
    table: np.ndarray


def _codes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashed trigrams of lower-cased bytes, ASCII marks and digits as blanks, in order; and offsets.

    Trigrams of blanks alone, and those across two texts, are left out.
    """
    data, off = kernel.bytes_of(texts)
    low = LETTERS[data].astype(np.uint32)
    if len(low) < 3:
        return np.zeros(0, dtype=np.int32), np.zeros(len(off), dtype=np.int64)
    a, b, c = low[:-2], low[1:-1], low[2:]
    code = (((a << np.uint32(16)) | (b << np.uint32(8)) | c) * np.uint32(2654435761) >> np.uint32(32 - 15)).astype(np.int32)
    keep = ((b != 32) | ((a != 32) & (c != 32))) & ~((a == 32) & (c == 32))
    ends = off[1:-1]
    for back in (1, 2):
        keep[(ends - back)[(ends - back >= 0) & (ends - back < len(keep))]] = False
    upto = np.concatenate([[0], np.cumsum(keep), [0, 0]])
    upto[-2:] = upto[-3]
    return code[keep], upto[off]


LETTERS = kernel.LOWER.copy()
LETTERS[:65] = LETTERS[91:97] = LETTERS[123:128] = 32


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts: dict[str, np.ndarray] = {}
    for batch in batches:
        declared = batch.column("declared").to_pylist()
        for at, to in kernel.portions(batch.column("text")):
            code, off = _codes(batch.column("text").slice(at, to - at))
            for row in range(to - at):
                own = counts.setdefault(declared[at + row], np.zeros(CODES + 1, dtype=np.int64))
                own[:CODES] += np.bincount(code[off[row] : off[row + 1]], minlength=CODES)
                own[CODES] += 1
    for name, own in counts.items():
        yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([own.tobytes()], pa.binary())], names=["declared", "counts"])


def _sample(rows: DataFrame, counts: dict[str, int], each: int) -> DataFrame:
    """Of each counted language the `each` rows of least hash; of frequent ones, only hashes that can be among them are sorted."""
    bounds = [(n, min(1.0, (2 * each + 40) / c)) for n, c in counts.items()]
    bounded = rows.join(F.broadcast(rows.sparkSession.createDataFrame(bounds, "declared string, share double")), "declared")
    near = bounded.withColumn("h", F.xxhash64("key", "text", F.lit("language")))
    near = near.where((F.col("share") >= 1) | (F.col("h").cast("double") / F.lit(float(1 << 64)) + 0.5 < F.col("share")))
    place = F.row_number().over(Window.partitionBy("declared").orderBy("h", "key", "text"))
    return near.withColumn("place", place).where(F.col("place") <= each).select("declared", "text")


def fit(rows: DataFrame, fit_rows: int = FIT_ROWS) -> TextModel:
    """A model of (key, text, declared) rows: languages by counts of all rows, each fitted on a bounded sample of its own."""
    said = rows.select("key", "text", F.lower("declared").alias("declared")).where("declared is not null and declared != ''")
    by_name = said.groupBy("declared").count()
    counts = {r["declared"]: r["count"] for r in by_name.where(F.col("count") >= FIT_LEAST).collect()}
    if not counts:
        only = by_name.limit(2).collect()
        counts = {r["declared"]: r["count"] for r in only} if len(only) == 1 else {}
    names = tuple(sorted(counts))
    total: dict[str, np.ndarray] = {}
    each = max(FIT_EACH, fit_rows // max(1, len(names)))
    for again in (False, True):  # equal rows have equal hashes, which can all lie beyond the bound: such languages are sorted whole
        left = {n: 1 for n in names if n not in total or total[n][CODES] < min(FIT_LEAST, counts[n])} if again else counts
        if left:
            parts = _sample(said, left, each).repartition(4, "declared").mapInArrow(_counted, "declared string, counts binary").collect()
            total |= {p["declared"]: np.frombuffer(p["counts"], dtype=np.int64) for p in parts}
    logs = [np.log((total[n][:CODES] + 0.1) / (total[n][:CODES].sum() + 0.1 * CODES)) for n in names]
    return TextModel(names, np.array([*logs, np.full(CODES, -math.log(CODES))], dtype=np.float64))


def _likelihoods(model: TextModel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at, to in kernel.portions(batch.column("text")):
                code, off = _codes(batch.column("text").slice(at, to - at))
                scores = np.array([kernel.sums(row[code], off) for row in model.table]).T
                lists = pa.ListArray.from_arrays(pa.array(np.arange(to - at + 1, dtype=np.int32) * scores.shape[1]), pa.array(np.ascontiguousarray(scores).reshape(-1)))
                named = [c.slice(at, to - at) for c, n in zip(batch.columns, batch.schema.names, strict=True) if n != "text"]
                data, at_byte = kernel.bytes_of(batch.column("text").slice(at, to - at))
                letters = kernel.sums((LETTERS[data] != 32).astype(np.int64), at_byte)
                yield pa.RecordBatch.from_arrays([*named, pa.array(letters), pa.array(np.diff(off)), lists], names=[n for n in batch.schema.names if n != "text"] + ["n_letters", "n_grams", "scores"])

    return run


def _counts(rows: DataFrame, by: str, n: int) -> DataFrame:
    """Rows of each value of `by` by their best language of the text alone."""
    return rows.where("guess is not null").groupBy(by).agg(F.array(*[F.count(F.when(F.col("guess") == i, 1)) for i in range(n)]).alias("counts"))


def _smoothed(counts: Column, parent: Column) -> Column:
    total = F.aggregate(counts, F.lit(0.0), lambda a, x: a + x)
    return F.zip_with(counts, parent, lambda c, p: (c + F.lit(HOST_WEIGHT) * p) / (total + HOST_WEIGHT))


def identify(rows: DataFrame, scratch: Scratch | None = None, fit_rows: int = FIT_ROWS) -> DataFrame:
    """Adds language, posterior and accepted to rows of (key, text, declared, suffix, host).

    The posterior of a language is the product of the text's likelihood (hashed
    byte trigrams, counted as no more than EVIDENCE of them), the chance of the
    declared language and of the suffix's hint, and the host's prior: counts of
    all rows of the host by their text's best language, smoothed with those of
    its suffix and these with those of all rows.  A further class, `und`, takes
    texts that every language explains worse than chance.  Texts without a letter are `und`,
    and those too short for a trigram go by the other evidence; unknown or null declarations and suffixes are no evidence; null hosts are one host.
    accepted: not `und`, and a posterior of at least ACCEPTED.  Every row is
    returned, without its text; repeated rows are rows of their own.
    """
    scratch = scratch or Scratch(rows.sparkSession, "language")
    model = fit(rows, fit_rows)
    names, n = model.languages, len(model.languages)
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.drop("text").schema)
    scored = rows.select(*[c for c in rows.columns if c != "text"], "text").mapInArrow(_likelihoods(model), f"{fields}, n_letters long, n_grams long, scores array<double>")
    scored = scratch.table(scored)
    if not n:
        return scored.select(*[c for c in rows.columns if c != "text"], F.lit("und").alias("language"), F.lit(0.0).alias("posterior"), F.lit(False).alias("accepted"))
    own = F.slice("scores", 1, n)
    guess = F.when((F.col("n_grams") > 0) & (F.array_max(own) > F.element_at("scores", n + 1)), F.array_position(own, F.array_max(own)) - 1)
    scored = scored.withColumn("guess", guess).withColumn("_suffix", F.coalesce("suffix", F.lit(""))).withColumn("_host", F.coalesce("host", F.lit("")))
    all_rows = scored.agg(*[F.count(F.when(F.col("guess") == i, 1)).alias(f"c{i}") for i in range(n)]).first()
    overall = F.array(*[F.lit((all_rows[i] + 1.0) / (sum(all_rows) + n)) for i in range(n)])
    by_suffix = _counts(scored, "_suffix", n).select("_suffix", _smoothed(F.col("counts"), overall).alias("above"))
    hosts = scored.where("guess is not null").groupBy("_host", "_suffix").agg(F.array(*[F.count(F.when(F.col("guess") == i, 1)) for i in range(n)]).alias("counts"))
    hosts = hosts.join(if_small(by_suffix, HOSTS_BROADCAST), "_suffix").select("_host", "_suffix", _smoothed(F.col("counts"), F.col("above")).alias("prior"))
    joined = scored.join(if_small(hosts, HOSTS_BROADCAST), ["_host", "_suffix"], "left")

    def chance(said: Column, right: float) -> Column:
        known = said.isin(*names)
        wrong = (1 - right) / max(1, n - 1)
        return F.array(*[F.when(known, F.when(said == name, math.log(right)).otherwise(math.log(wrong))).otherwise(0.0) for name in names], F.when(known, math.log(1 / n)).otherwise(0.0))

    hint = F.create_map(*[F.lit(x) for kv in SUFFIXES.items() for x in kv])[F.coalesce(F.col("suffix"), F.lit(""))]
    weight = F.least(F.lit(1.0), F.lit(EVIDENCE) / F.greatest(F.col("n_grams"), F.lit(1)))
    prior = F.concat(F.transform(F.coalesce(F.col("prior"), overall), lambda p: F.log(p * (1 - UNKNOWN))), F.array(F.lit(math.log(UNKNOWN))))
    add = lambda a, b: F.zip_with(a, b, lambda x, y: x + y)
    total = add(add(F.transform("scores", lambda s: s * weight), prior), add(chance(F.lower("declared"), DECLARED_RIGHT), chance(hint, SUFFIX_RIGHT)))
    done = joined.withColumn("_total", total).withColumn("_most", F.array_max("_total")).withColumn("_best", F.array_position("_total", F.col("_most")).cast("int"))
    shares = F.aggregate("_total", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("_most")))
    done = done.withColumn("language", F.when(F.col("n_letters") == 0, "und").otherwise(F.element_at(F.array(*map(F.lit, [*names, "und"])), F.col("_best")))).withColumn("posterior", F.when(F.col("n_letters") == 0, 0.0).otherwise(1.0 / shares))
    return done.select(*[c for c in rows.columns if c != "text"], "language", "posterior", ((F.col("language") != "und") & (F.col("posterior") >= ACCEPTED)).alias("accepted"))


def of_documents(docs: DataFrame, *more: Column) -> DataFrame:
    """Documents as rows for `identify`: their source is the host, and they have no address."""
    return docs.select(*more, F.col("doc_id").alias("key"), "text", F.col("lang").alias("declared"), F.lit(None).cast("string").alias("suffix"), F.col("source").alias("host"))


def of_pages(pages: DataFrame) -> DataFrame:
    """Pages as rows for `identify`: the markup's lang attribute, the host and its last part."""
    declared = F.lower(F.regexp_extract(F.coalesce("html", F.lit("")), r"(?i)<html[^>]*\slang=[\"']?([a-z]{2,3})", 1))
    host = host_of(F.col("url"))
    return pages.select(F.col("page_id").alias("key"), F.array_join(lines_of(F.col("html")), "\n").alias("text"), F.nullif(declared, F.lit("")).alias("declared"), F.nullif(F.substring_index(host, ".", -1), F.lit("")).alias("suffix"), host.alias("host"))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document."""
    found = identify(of_documents(table(spark, sf_dir, "documents")))
    return found.select(F.col("key").alias("doc_id"), "declared", "language", "posterior", "accepted")


def page_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every page, by its text, markup, address and host."""
    found = identify(of_pages(table(spark, sf_dir, "pages")))
    return found.select(F.col("key").alias("page_id"), "host", "suffix", "declared", "language", "posterior", "accepted")


def keep_identified(docs: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """The rows of docs whose language is accepted.  Each row is judged on its own, whatever its doc_id."""
    mark = F.xxhash64(*[F.coalesce(F.col(c), F.lit("")) for c in ("text", "lang", "source")])
    found = identify(of_documents(docs, mark.alias("mark")), scratch)
    rejected = found.where("not accepted").select(F.col("key").alias("rejected"), F.col("mark").alias("rejected_mark")).distinct()
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col("doc_id").alias("key"), mark.alias("mark"))
    left = own.join(if_small(rejected, 1_000_000), F.col("key").eqNullSafe(F.col("rejected")) & (F.col("mark") == F.col("rejected_mark")), "left_anti")
    return left.select(*[F.col("row")[c].alias(c) for c in docs.columns])
