"""Mixing sources to target weights by Poisson replication."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.llm.common import digest, draw, free_name, if_small, table

#: A Poisson number of a larger mean is the sum of several of at most this mean.
MEAN_A_DRAW = 64.0
#: Up to so many sources, their rates are broadcast; beyond it they are joined by shuffle.
SOURCES_BROADCAST = 20_000


def source_rates(docs: DataFrame, source: str = "source", text: str = "text", weights: Mapping[str | None, float] | None = None, power: float | None = None, epochs: float = 1.0) -> DataFrame:
    """(mix_source, rate): the mean number of times that each row of a source is to be repeated.

    A source's target share is its weight over all weights; without weights, the
    weight is the square root of its bytes (`power` for another exponent).  A source that `weights` does not
    name has weight 0.  A row's size is its text's UTF-8 bytes plus 1, so that
    empty texts count; null sources are one source of their own.
    """
    docs = docs.select(F.col(source).alias("mix_source"), F.col(text).alias("mix_text"))
    sizes = docs.groupBy("mix_source").agg(F.sum(F.coalesce(F.octet_length("mix_text"), F.lit(0)) + F.lit(1)).cast("double").alias("bytes"))
    if weights is None:
        weighted = sizes.withColumn("weight", F.sqrt("bytes") if power is None else F.pow("bytes", F.lit(power)))
    else:
        given = docs.sparkSession.createDataFrame([(k, float(v)) for k, v in weights.items()], "name string, weight double")
        weighted = sizes.join(F.broadcast(given), F.col("mix_source").eqNullSafe(F.col("name")), "left").select("mix_source", "bytes", F.coalesce("weight", F.lit(0.0)).alias("weight"))
    total = weighted.agg(F.sum("bytes").alias("all_bytes"), F.sum("weight").alias("all_weight")).withColumn("_one", F.lit(1))
    return weighted.withColumn("_one", F.lit(1)).join(F.broadcast(total), "_one").select("mix_source", F.coalesce(F.lit(epochs) * F.col("all_bytes") * (F.col("weight") / F.nullif(F.col("all_weight"), F.lit(0.0))) / F.col("bytes"), F.lit(0.0)).alias("rate"))


def _cumulative(rates: DataFrame) -> DataFrame:
    """Adds the number of draws and the cumulative probabilities of one draw."""
    drawn = rates.withColumn("draws", F.greatest(F.lit(1), F.ceil(F.col("rate") / MEAN_A_DRAW)).cast("int")).withColumn("mean", F.col("rate") / F.col("draws"))
    start = F.struct(F.exp(-F.col("mean")).alias("p"), F.array(F.exp(-F.col("mean"))).alias("upto"))

    def add(a, k):
        p = a["p"] * F.col("mean") / k
        return F.struct(p.alias("p"), F.array_append(a["upto"], F.element_at(a["upto"], -1) + p).alias("upto"))

    terms = F.sequence(F.lit(1), F.ceil(F.col("mean") + 12 * F.sqrt("mean") + 20).cast("int"))
    return drawn.select("mix_source", "draws", F.aggregate(terms, start, add, lambda a: a["upto"]).alias("upto"))


def mix(docs: DataFrame, key: str = "doc_id", source: str = "source", text: str = "text", seed: str = "mix", **rates) -> DataFrame:
    """Repeats each row a Poisson number of times and shuffles all copies.

    The number is the Poisson distribution of the source's rate, inverted at a draw
    fixed by seed and key, so that a run again, or on other machines, gives the
    same copies.  Returns the columns of docs, copy_no (from 1) and mix_key, which get underscores behind their names where docs has columns of these; rows
    are dealt out and sorted by mix_key, the order to read them in.  Rows with
    equal keys draw alike; a null key is one key.  Nothing is capped.
    """
    upto = if_small(_cumulative(source_rates(docs, source, text, **rates)), SOURCES_BROADCAST)
    names = docs.columns  # a row goes along whole, so that no name of its columns can clash with one used here
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), F.col(key).alias("row_key"), F.col(source).alias("row_source"))
    joined = own.join(upto, F.col("row_source").eqNullSafe(F.col("mix_source")))
    count = F.aggregate(
        F.sequence(F.lit(1), F.col("draws")), F.lit(0), lambda n, j: n + F.size(F.filter("upto", lambda c: c <= draw(seed, F.col("row_key"), j)))
    )
    copies = joined.withColumn("n", count).where("n > 0").select("row", "row_key", F.explode(F.sequence(F.lit(1), F.col("n"))).alias("copy"))
    keyed = copies.select("row", "copy", digest(seed, "order", F.col("row_key"), F.col("copy"), digits=15).alias("place"))
    dealt = keyed.repartition("place").sortWithinPartitions("place")
    return dealt.select(*[F.col("row")[c].alias(c) for c in names], F.col("copy").alias(free_name(names, "copy_no")), F.col("place").alias(free_name(names, "mix_key")))


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, mixed so that a source's share goes with the square root of its bytes, one epoch in all."""
    return mix(table(spark, sf_dir, "documents"))


ORACLE = """
WITH RECURSIVE sizes AS (
  SELECT source, CAST(sum(coalesce(octet_length(encode(text)), 0) + 1) AS DOUBLE) AS bytes FROM documents GROUP BY source
), weighted AS (SELECT source, bytes, sqrt(bytes) AS weight FROM sizes
), rates AS (
  SELECT source, (SELECT sum(bytes) FROM weighted) * (weight / (SELECT sum(weight) FROM weighted)) / bytes AS rate FROM weighted
), drawn AS (
  SELECT source, greatest(1, ceil(rate / 64.0))::INTEGER AS draws, rate / greatest(1, ceil(rate / 64.0)) AS mean FROM rates
), terms(source, draws, mean, k, p, upto) AS (
  SELECT source, draws, mean, 0, exp(-mean), exp(-mean) FROM drawn
  UNION ALL
  SELECT source, draws, mean, k + 1, p * mean / (k + 1), upto + p * mean / (k + 1) FROM terms
  WHERE k < ceil(mean + 12 * sqrt(mean) + 20)
), dists AS (SELECT source, any_value(draws) AS draws, list(upto) AS upto FROM terms GROUP BY source
), draws AS (
  SELECT d.doc_id, d.text, d.lang, d.source, d.n_chars, t.upto, t.draws FROM documents d JOIN dists t ON d.source IS NOT DISTINCT FROM t.source
), counted AS (
  SELECT doc_id, text, lang, source, n_chars, CAST(list_sum(list_transform(range(1, draws + 1), lambda j:
    len(list_filter(upto, lambda c: c <= ('0x' || substr(md5('mix|' || coalesce(doc_id::VARCHAR, '') || '|' || j), 1, 13))::BIGINT / 4503599627370496.0)))) AS INTEGER) AS n
  FROM draws
), copies AS (
  SELECT doc_id, text, lang, source, n_chars, CAST(unnest(range(1, n + 1)) AS INTEGER) AS copy_no FROM counted WHERE n > 0
)
SELECT *, ('0x' || substr(md5('mix|order|' || coalesce(doc_id::VARCHAR, '') || '|' || copy_no), 1, 15))::BIGINT AS mix_key FROM copies
"""
