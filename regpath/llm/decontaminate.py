"""Benchmark decontamination by spaced seeds."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.llm.common import if_small, quick_words, small, table

#: A seed compares the words where its mask has 1 and ignores the others; all masks are equally long.
MASKS = ("11011010111", "11101011011")
#: An overlap counts if at least this share of the item's words stand in their places.
OVERLAP = 0.5
#: So does a stretch of AROUND words from a hit on, if this share of them stands in place, however long the item.
AROUND, AROUND_SHARE = 20, 0.8
#: Up to so many benchmark seeds, they are broadcast; beyond it they are joined by shuffle.
SEEDS_BROADCAST = 500_000
#: Up to so many texts that overlap are told by a broadcast of their hashes.
HITS_BROADCAST = 500_000


def _hash_at(words: Column, start: Column, mask: str) -> Column:
    """Hash of the words that the mask compares; start counts from 0."""
    return F.xxhash64(F.lit(mask), *[words[start + i] for i, bit in enumerate(mask) if bit == "1"])


def seeds_of(rows: DataFrame, words: str, masks=MASKS) -> DataFrame:
    """Adds pos and seed: a row for each place and mask; texts shorter than a mask have none (see `_short`)."""
    span = F.lit(len(masks[0]))
    placed = rows.where(F.size(words) >= span).withColumn("pos", F.explode(F.sequence(F.lit(0), F.size(words) - span)))
    return placed.withColumn("seed", F.explode(F.array(*[_hash_at(F.col(words), F.col("pos"), m) for m in masks])))


def matched(doc: Column, item: Column, shift: Column) -> Column:
    """In how many places the item, laid on the document from word `shift` on, agrees with it."""
    skip = F.greatest(-shift, F.lit(0))
    n = F.greatest(F.least(F.size(item) - skip, F.size(doc) - F.greatest(shift, F.lit(0))), F.lit(0))
    pairs = F.zip_with(F.slice(doc, F.greatest(shift, F.lit(0)) + 1, n), F.slice(item, skip + 1, n), lambda a, b: a == b)
    return F.size(F.filter(pairs, lambda x: x))


def around(doc: Column, item: Column, at_doc: Column, at_item: Column) -> Column:
    """How many of the AROUND words from a hit on are equal; those beyond either text are not."""
    pairs = F.zip_with(F.slice(doc, at_doc + 1, AROUND), F.slice(item, at_item + 1, AROUND), lambda a, b: a == b)
    return F.size(F.filter(pairs, lambda x: F.coalesce(x, F.lit(False))))


def overlaps(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", overlap: float = OVERLAP, masks=MASKS, broadcast_up_to: int = SEEDS_BROADCAST) -> DataFrame:
    """(key, item, matched, item_words, overlap, around, start) for each document and item that overlap.

    The item is laid on the document so that one of its seeds meets an equal
    one; words that differ are substitutions.  overlap: the share of the item's
    words that stand in their places; the best lay, then the first, is
    returned.  around: the most equal words of the AROUND from one of the hits on.  They overlap if `overlap` of the
    item's words are in place, or AROUND_SHARE of those around a hit: a part of a long item, or a copy with
    words put in or left out between parts, is found by the latter.  start: the document's word, from 0, on which the item's first
    word lies.  An item of fewer words than a mask, but of three at least, must stand unchanged, and
    a shorter one must be the whole document.
    Null and empty texts overlap with nothing; equal keys count as one document.
    """
    if len({len(m) for m in masks}) != 1:
        raise ValueError("masks must be equally long")
    span = len(masks[0])
    own = docs.select(F.col(key).alias("_key"), quick_words(F.col(text)).alias("_words"))
    items = benchmark.select(F.col(item).alias("_item"), quick_words(F.col(item_text)).alias("_item_words")).where(F.size("_item_words") > 0)
    seeds = seeds_of(items, "_item_words", masks).select("_item", "_item_words", F.col("pos").alias("_item_pos"), "seed")
    if small(seeds, broadcast_up_to):
        hits = seeds_of(own, "_words", masks).join(F.broadcast(seeds), "seed").withColumn("_shift", F.col("pos") - F.col("_item_pos"))
        near = around(F.col("_words"), F.col("_item_words"), F.col("pos"), F.col("_item_pos"))
    else:
        thin = seeds_of(own, "_words", masks).select("_key", "pos", "seed").join(seeds.drop("_item_words"), "seed")
        # one lay has at most as many hits as the item has words
        thin = thin.groupBy("_key", "_item", (F.col("pos") - F.col("_item_pos")).alias("_shift")).agg(F.collect_set("pos").alias("_places"))
        hits = thin.join(items, "_item").join(own, "_key")
        near = F.array_max(F.transform("_places", lambda p: around(F.col("_words"), F.col("_item_words"), p, p - F.col("_shift"))))
    found = hits.select("_key", "_item", F.size("_item_words").alias("item_words"), "_shift", matched(F.col("_words"), F.col("_item_words"), F.col("_shift")).alias("matched"), near.alias("around"))
    short = items.where(F.size("_item_words") < span)
    if small(short, 0) is False:
        found = found.union(_short(own, short, span))
    # the threshold stands behind the maximum: as a condition of the join it would copy each document's words for each of its seeds
    best = found.groupBy("_key", "_item", "item_words").agg(F.max(F.struct("matched", (-F.col("_shift")).alias("back"))).alias("best"), F.max("around").alias("around"))
    best = best.where((F.col("best.matched") >= F.lit(overlap) * F.col("item_words")) | (F.col("around") >= AROUND_SHARE * AROUND))
    return best.select(
        F.col("_key").alias(key), F.col("_item").alias(item), F.col("best.matched").alias("matched"), "item_words", (F.col("best.matched") / F.col("item_words")).alias("overlap"), "around", (-F.col("best.back")).alias("start")
    )


def _short(own: DataFrame, short: DataFrame, span: int) -> DataFrame:
    """Places of items that are shorter than a mask, compared word by word through one hash for each length."""
    lengths = F.array(*[F.lit(n) for n in range(3, span)])
    placed = own.withColumn("_n", F.explode(lengths)).where(F.size("_words") >= F.col("_n")).withColumn("_shift", F.explode(F.sequence(F.lit(0), F.size("_words") - F.col("_n"))))
    run = placed.select("_key", "_shift", F.slice("_words", F.col("_shift") + 1, F.col("_n")).alias("_item_words"))
    whole = own.where(F.size("_words").between(1, 2)).select("_key", F.lit(0).alias("_shift"), F.col("_words").alias("_item_words"))
    return run.union(whole).join(short, "_item_words").select("_key", "_item", F.size("_item_words").alias("item_words"), "_shift", F.size("_item_words").alias("matched"), F.size("_item_words").alias("around"))


def clean(docs: DataFrame, benchmark: DataFrame, text: str = "text", **how) -> DataFrame:
    """The rows of docs whose text overlaps with no item.  Texts are told by 128 bits of hash; keys, or none, play no part."""
    words = F.coalesce(F.col(text), F.lit(""))
    mark = F.struct(F.xxhash64(words).alias("a"), F.xxhash64(F.lit("again"), words).alias("b"))
    hit = overlaps(docs.select(mark.alias("mark"), F.col(text).alias("text")), benchmark, "mark", **how).select(F.col("mark").alias("hit")).distinct()
    own = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), mark.alias("mark"))
    left = own.join(if_small(hit, HITS_BROADCAST), F.col("mark") == F.col("hit"), "left_anti")
    return left.select(*[F.col("row")[c].alias(c) for c in docs.columns])


def op4_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents against all benchmark items."""
    return overlaps(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def _sql() -> str:
    words = "list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '')"
    span = len(MASKS[0])
    keys = "unnest([" + ", ".join(f"'{m}' || ' ' || " + " || ' ' || ".join(f"w[p + {i + 1}]" for i, b in enumerate(m) if b == "1") for m in MASKS) + "])"
    return f"""
WITH d AS (SELECT doc_id, {words} AS w FROM documents), b AS (SELECT item_id, {words} AS w FROM benchmark),
ds AS (SELECT doc_id, p, {keys} AS k FROM (SELECT doc_id, w, unnest(range(0, len(w) - {span - 1})) AS p FROM d)),
bs AS (SELECT item_id, p, {keys} AS k FROM (SELECT item_id, w, unnest(range(0, len(w) - {span - 1})) AS p FROM b)),
hits AS (
  SELECT DISTINCT ds.doc_id, bs.item_id, ds.p - bs.p AS shift, ds.p AS p FROM ds JOIN bs USING (k)
), near AS (
  SELECT h.doc_id, h.item_id, h.shift, max(len(list_filter(range(0, {AROUND}), lambda i: h.p + i < len(d.w) AND h.p - h.shift + i < len(b.w) AND b.w[h.p - h.shift + i + 1] = d.w[h.p + i + 1]))) AS a
  FROM hits h JOIN d USING (doc_id) JOIN b USING (item_id) GROUP BY ALL
), laid AS (
  SELECT h.doc_id, h.item_id, h.shift, h.a, len(b.w) AS n, len(list_filter(range(0, len(b.w)), lambda i: i + h.shift >= 0 AND i + h.shift < len(d.w) AND b.w[i + 1] = d.w[i + h.shift + 1])) AS m
  FROM near h JOIN d USING (doc_id) JOIN b USING (item_id)
  UNION ALL
  SELECT doc_id, item_id, shift, n, n, n FROM (
    SELECT d.doc_id, b.item_id, unnest(range(0, len(d.w) - len(b.w) + 1)) AS shift, len(b.w) AS n, d.w AS dw, b.w AS bw
    FROM d, b WHERE len(b.w) BETWEEN 3 AND {span - 1} AND list_has_all(d.w, b.w)
  ) WHERE dw[shift + 1 : shift + n] = bw
  UNION ALL
  SELECT doc_id, item_id, 0, len(b.w), len(b.w), len(b.w) FROM d JOIN b USING (w) WHERE len(b.w) BETWEEN 1 AND 2
), best AS (
  SELECT doc_id, item_id, m, n, shift, max(a) OVER (PARTITION BY doc_id, item_id) AS a, row_number() OVER (PARTITION BY doc_id, item_id ORDER BY m DESC, shift) AS r FROM laid
)
SELECT doc_id, item_id, m::INTEGER AS matched, n::INTEGER AS item_words, m / n::DOUBLE AS overlap, a::INTEGER AS around, shift::INTEGER AS start FROM best WHERE r = 1 AND (m >= {OVERLAP} * n OR a >= {AROUND_SHARE * AROUND})
"""


ORACLE = _sql()
