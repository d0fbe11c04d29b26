"""License scans: exact phrases, and an exact set-similarity join with templates."""

from __future__ import annotations

from collections.abc import Callable, Mapping

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from regpath.llm.common import if_small, quick_words, table, words_of
from regpath.operators.scratch import Scratch

#: Phrases and their labels.
PHRASES = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: Usual notices and license texts, as lower-case words, and their labels.
TEMPLATES = (
    ("mit", "released under the mit license"),
    ("mit", "licensed under the mit license see the license file for details"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files to deal in the software without restriction"),
    ("apache-2", "licensed under the apache license version 2 0"),
    ("apache-2", "you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0"),
    ("gpl-3", "this work is licensed under the gnu general public license version 3"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by-nc", "this work is licensed under a creative commons attribution noncommercial 4 0 international license"),
    ("cc-by", "this work is licensed under a creative commons attribution 4 0 international license"),
    ("cc-by-sa", "this work is licensed under a creative commons attribution sharealike 4 0 international license"),
    (
        "mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions "
        "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software "
        "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
    ),
    (
        "isc",
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies "
        "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of or in connection with the use or performance of this software",
    ),
)
CONTAINED = 0.9
#: Texts are cut into blocks of twice HALF words that start at every multiple of it, so each run of HALF words lies in one; longer templates take blocks of twice, four times, ... the size.
HALF = 64
#: Up to so many template words are broadcast; beyond it they are joined by shuffle.
WORDS_BROADCAST = 200_000


def templates_of(spark: SparkSession, templates=TEMPLATES) -> DataFrame:
    """(label, text) rows as a table."""
    return spark.createDataFrame([(label, text) for label, text in templates], "label string, text string")


def blocks_of(words: Column, half: Column) -> Column:
    """(no, words) of the overlapping blocks of a whole text's words; one block for a text of fewer."""
    last = F.greatest(F.lit(0), F.ceil(F.size(words) / half) - 2).cast("int")
    return F.transform(F.sequence(F.lit(0), last), lambda i: F.struct(i.alias("no"), F.slice(words, i * half + 1, 2 * half).alias("words")))


def ranked(templates: DataFrame, docs: DataFrame, text: str, contained: float) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """(token, rank), the rarest in all docs first, and what makes of them (id, label, half, own, n, need) of each template, own being its sorted ranks.

    Their size is that of the templates, whatever the number of documents.
    """
    words = templates.select("label", words_of(F.col("text")).alias("w")).where(F.size("w") > 0)
    words = words.withColumn("id", F.xxhash64("label", "w")).distinct()
    tokens = words.select(F.explode("w").alias("token")).distinct()
    seen = docs.select(F.explode(quick_words(F.col(text))).alias("token")).join(if_small(tokens, WORDS_BROADCAST), "token").groupBy("token").count()
    place = F.row_number().over(Window.orderBy(F.coalesce("count", F.lit(0)), "token"))
    rank = tokens.join(seen, "token", "left").select("token", place.alias("rank"))
    half = F.lit(HALF) * F.pow(F.lit(2.0), F.greatest(F.lit(0.0), F.ceil(F.log2(F.size("w") / F.lit(float(HALF))) - 1e-9)))
    def sets(rank: DataFrame) -> DataFrame:
        own = words.select("id", "label", half.cast("int").alias("half"), F.explode(F.array_distinct("w")).alias("token")).join(rank, "token")
        each = own.groupBy("id", "label", "half").agg(F.sort_array(F.collect_list("rank")).alias("own")).withColumn("n", F.size("own"))
        return each.withColumn("need", F.ceil(F.lit(contained) * F.col("n") - 1e-9).cast("int"))

    return rank, sets


def contained_in(docs: DataFrame, templates: DataFrame, text: str = "text", contained: float = CONTAINED, scratch: Scratch | None = None) -> DataFrame:
    """(mark, label, share) of each text, known by its mark, and each template that one of its blocks contains.

    An exact set-similarity join.  Words are ordered by their frequency in all
    docs.  A block that holds `need` of a template's n words holds one of its n - need + 1 rarest, so
    blocks meet templates at these words only; the block must be large enough,
    and both sides must have enough words from the first they share on.  What is left is compared in full.
    """
    scratch = scratch or Scratch(docs.sparkSession, "licenses")
    rank, sets = ranked(templates, docs, text, contained)
    rank = scratch.table(rank)
    sets = scratch.table(sets(rank))
    heads = sets.select("*", F.posexplode(F.slice("own", F.lit(1), F.col("n") - F.col("need") + 1)).alias("at", "rank"))
    rare = rank.join(heads.select("rank").distinct(), "rank", "left_semi").select("token")
    marked = docs.select(mark_of(F.col(text)).alias("mark"), F.col(text).alias("text"))
    # most texts have no word of a head: they are told by their words in any lower case, and need no more
    told = marked.select("mark", F.explode(F.array_distinct(quick_words(F.col("text")))).alias("token")).join(if_small(rare, WORDS_BROADCAST), "token", "left_semi").select("mark").distinct()
    some = marked.join(if_small(told, WORDS_BROADCAST), "mark", "left_semi").dropDuplicates(["mark"])
    sizes = F.array(*[F.lit(h) for h in sorted({r["half"] for r in sets.select("half").distinct().collect()})] or [F.lit(HALF)])
    blocks = some.select("mark", words_of(F.col("text")).alias("w")).select("mark", "w", F.explode(sizes).alias("half"))
    blocks = blocks.select("mark", "half", F.explode(blocks_of(F.col("w"), F.col("half"))).alias("block"))
    found = blocks.select("mark", "half", "block.no", F.explode(F.array_distinct("block.words")).alias("token")).join(if_small(rank, WORDS_BROADCAST), "token")
    block = found.groupBy("mark", "half", "no").agg(F.sort_array(F.collect_list("rank")).alias("b")).withColumn("m", F.size("b"))
    placed = block.select("*", F.posexplode("b").alias("pos", "rank")).join(if_small(heads, WORDS_BROADCAST), ["half", "rank"])
    near = placed.where((F.col("m") >= F.col("need")) & (F.least(F.col("n") - F.col("at"), F.col("m") - F.col("pos")) >= F.col("need")))
    both = near.select("mark", "label", "n", "need", F.size(F.array_intersect("own", "b")).alias("both"))
    return both.where(F.col("both") >= F.col("need")).groupBy("mark", "label").agg(F.max(F.col("both") / F.col("n")).alias("share"))


def mark_of(text: Column) -> Column:
    """128 bits of a text; null counts as empty."""
    body = F.coalesce(text, F.lit(""))
    return F.struct(F.xxhash64(body).alias("a"), F.xxhash64(F.lit("again"), body).alias("b"))


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", phrases: Mapping[str, str] = PHRASES, templates=TEMPLATES, contained: float = CONTAINED) -> DataFrame:
    """(key, n_words, n_base, first_word, last_word, base_labels, labels, score) for each row.

    A phrase counts wherever its words stand consecutively.  A block of words
    matches a template if it holds at least `contained` of the template's
    distinct words (see `contained_in`).  templates: pairs, or a table of (label, text) with texts of any length.
    score: the largest share found, 1 with a phrase.
    Null and empty texts have no words and no labels.  Each row is on its own:
    repeated rows and equal keys are returned as often as they occur.
    """
    given = templates if isinstance(templates, DataFrame) else templates_of(docs.sparkSession, templates)
    own = docs.select(F.col(key).alias("k"), F.col(text).alias("text"))
    method = contained_in(own, given, "text", contained).groupBy("mark").agg(F.collect_set("label").alias("more"), F.max("share").alias("share"))
    # words and places are only worked out where each word of a phrase stands somewhere
    low = F.lower("text")
    may = None
    for phrase in phrases:
        here = None
        for word in phrase.split():
            here = low.contains(word) if here is None else here & low.contains(word)
        may = here if may is None else may | here
    words = own.select("k", "text", F.size(quick_words(F.col("text"))).alias("n"), F.coalesce(may, F.lit(False)).alias("told"))
    spaced = words.withColumn("s", F.when(F.col("told"), F.concat(F.lit(" "), F.array_join(words_of(F.col("text")), "  "), F.lit(" "))).otherwise(F.lit("")))

    def spaces(x: Column) -> Column:
        return (F.length(x) - F.length(F.replace(x, F.lit(" "), F.lit("")))) / 2

    out, count, first, last, base = spaced, F.lit(0), [], [], []
    for i, (phrase, label) in enumerate(phrases.items()):
        k, pattern = len(phrase.split()), " " + "  ".join(phrase.split()) + " "
        here = F.col("s").contains(pattern)
        places = F.when(here, (F.length("s") - F.length(F.replace(F.col("s"), F.lit(pattern), F.lit("")))) / len(pattern)).otherwise(0)
        out = out.withColumn(f"c{i}", places.cast("long"))
        count = count + F.col(f"c{i}")
        first.append(F.when(here, spaces(F.substring_index("s", pattern, 1))))
        last.append(F.when(here, F.col("n") - k - spaces(F.substring_index("s", pattern, -1))))
        base.append(F.when(here, F.lit(label)))
    out = out.withColumn("mark", mark_of(F.col("text"))).withColumn("base", F.array_compact(F.array(*base)))
    out = out.join(if_small(method, WORDS_BROADCAST), "mark", "left").withColumn("more", F.coalesce("more", F.array().cast("array<string>")))
    label = lambda a: F.array_join(F.array_sort(F.array_distinct(a)), ",")
    ends = lambda f, xs: (f(*xs) if len(xs) > 1 else xs[0]).cast("long")
    return out.select(
        F.col("k").alias(key), F.col("n").cast("long").alias("n_words"), count.cast("long").alias("n_base"), ends(F.least, first).alias("first_word"), ends(F.greatest, last).alias("last_word"),
        label(F.col("base")).alias("base_labels"), label(F.concat("base", "more")).alias("labels"), F.greatest(F.when(F.size("base") > 0, 1.0).otherwise(0.0), F.coalesce("share", F.lit(0.0))).alias("score"),
    )


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Phrases and templates in all documents."""
    return scan(table(spark, sf_dir, "documents"))


def _sql() -> str:
    halves = [next(HALF << c for c in range(99) if len(t.split()) <= HALF << c) for _, t in TEMPLATES]
    known = ", ".join(f"('{label}', {half}, string_split('{t}', ' '))" for half, (label, t) in zip(halves, TEMPLATES, strict=True))
    phrases = ", ".join(f"('{label}', string_split('{p}', ' '))" for p, label in PHRASES.items())
    return f"""
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '') AS w FROM documents
), t AS (SELECT label, half, list_distinct(ws) AS ws FROM (VALUES {known}) v(label, half, ws)
), p AS (SELECT label, ws FROM (VALUES {phrases}) v(label, ws)
), places AS (
  SELECT doc_id, label, i FROM (SELECT doc_id, w, label, ws, unnest(range(0, len(w) - len(ws) + 1)) AS i FROM w, p WHERE list_has_all(w, ws))
  WHERE w[i + 1 : i + len(ws)] = ws
), base AS (
  SELECT doc_id, count(*) AS n_base, min(i) AS first_word, max(i) AS last_word, list(DISTINCT label) AS ls FROM places GROUP BY doc_id
), blocks AS (
  SELECT doc_id, half, list_distinct(w[half * i + 1 : half * i + 2 * half]) AS b
  FROM (SELECT doc_id, w, half, unnest(range(0, greatest(0, ceil(len(w) / half::DOUBLE)::BIGINT - 2) + 1)) AS i FROM w, (SELECT DISTINCT half FROM t))
), near AS (
  SELECT doc_id, label, len(list_intersect(b, ws)) / len(ws)::DOUBLE AS share FROM blocks JOIN t USING (half) WHERE len(list_intersect(b, ws)) >= ceil({CONTAINED} * len(ws) - 1e-9)
), method AS (SELECT doc_id, list(DISTINCT label) AS ls, max(share) AS share FROM near GROUP BY doc_id)
SELECT w.doc_id, len(w.w)::BIGINT AS n_words, coalesce(n_base, 0)::BIGINT AS n_base, first_word, last_word,
  coalesce(array_to_string(list_sort(base.ls), ','), '') AS base_labels,
  coalesce(array_to_string(list_sort(list_distinct(list_concat(coalesce(base.ls, []), coalesce(method.ls, [])))), ','), '') AS labels,
  greatest(CASE WHEN n_base > 0 THEN 1.0 ELSE 0.0 END, coalesce(share, 0.0))::DOUBLE AS score
FROM w LEFT JOIN base USING (doc_id) LEFT JOIN method USING (doc_id)
"""


ORACLE = _sql()
