"""What the operators share: word rules, hash draws, sizes that decide a broadcast."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Characters that part words: ASCII other than digits and small letters (texts are lower-cased first).
BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def lowered(text: Column) -> Column:
    """A-Z to a-z, all else as it is; null as the empty text."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def words_of(text: Column) -> Column:
    """Words of a text, lower-cased, as an array; none for null or empty texts."""
    return F.array_remove(F.split(lowered(text), BREAKS), "")


def quick_words(text: Column) -> Column:
    """Like words_of, with all letters in lower case, at half its cost: as many words, and the same ASCII ones or more."""
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), BREAKS), "")


def draw(*parts: Column | str) -> Column:
    """A number in [0, 1) fixed by the parts: 52 bits of their MD5.  Nulls count as the empty text."""
    return digest(*parts).cast("double") / F.lit(float(1 << 52))


def digest(*parts: Column | str, digits: int = 13) -> Column:
    """A long of 4 * digits bits fixed by the parts."""
    joined = F.concat_ws("|", *[F.coalesce(p.cast("string"), F.lit("")) if isinstance(p, Column) else F.lit(p) for p in parts])
    return F.conv(F.substring(F.md5(joined), 1, digits), 16, 10).cast("long")


def free_name(columns: list[str], name: str) -> str:
    """The name, with underscores behind it while a column has it."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def small(df: DataFrame, most: int) -> bool:
    """Whether df has at most so many rows; reads no further than that."""
    return df.limit(most + 1).count() <= most


def if_small(df: DataFrame, most: int) -> DataFrame:
    """df, to be broadcast if it has at most so many rows; else as it is, for a shuffled join."""
    return F.broadcast(df) if small(df, most) else df
