"""Line dedup: lines that most pages of a site repeat are dropped."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.llm.common import if_small, table
from regpath.operators.scratch import Scratch

HIDDEN = r"(?is)<(?:script|style)[^>]*>.*?</(?:script|style)>|<!--.*?-->"
BREAKING = r"(?i)</?(?:p|div|li|ul|ol|nav|article|section|header|footer|h[1-6]|br|tr|td|th|table|title|head|body|html|blockquote|pre|main|aside|form)(?:[ \t\r\n][^>]*)?/?>"
TAG, BLANK, PARTED = r"<[^>]*>", r"[ \t\r]+", r" ?\n[ \n]*"
#: Named characters of markup; the ampersand comes last.
NAMED = {"&nbsp;": " ", "&lt;": "<", "&gt;": ">", "&quot;": '"', "&#39;": "'", "&copy;": "©", "&middot;": "·", "&amp;": "&"}
HOST = r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]*)"
RATIO, LEAST_PAGES = 0.3, 3
#: Up to so many repeated lines in all, they are broadcast; beyond it they are joined by host.
LINES_BROADCAST = 200_000


def host_of(url: Column) -> Column:
    """The host of an address in lower case; the empty text if there is none."""
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), HOST, 1))


def lines_of(html: Column) -> Column:
    """Visible lines of a page: block markup and line ends part them, blanks are squeezed, empty ones left out."""
    shown = F.regexp_replace(F.coalesce(html, F.lit("")), HIDDEN, " ")
    plain = F.regexp_replace(F.regexp_replace(shown, BREAKING, "\n"), TAG, "")
    for name, char in NAMED.items():
        plain = F.replace(plain, F.lit(name), F.lit(char))
    return F.array_remove(F.transform(F.split(F.regexp_replace(plain, BLANK, " "), PARTED), lambda x: F.trim(x)), "")


def repeated_lines(pages: DataFrame, ratio: float, least_pages: int) -> DataFrame:
    """(host, lines): hashes of the lines that at least `ratio` of the host's pages and `least_pages` of them hold.

    Lines are counted by (host, line) with a partial count before the shuffle,
    so neither a large host nor a frequent line meets in one task.  A host's
    list is bounded by its mean number of lines a page over `ratio`.
    """
    each = pages.select("_host", F.explode(F.array_distinct(F.transform("_lines", line_hash))).alias("line"))
    counts = each.groupBy("_host", "line").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= least_pages)
    totals = pages.groupBy("_host").agg(F.count(F.lit(1)).alias("pages")).where(F.col("pages") >= least_pages)
    often = counts.join(totals, "_host").where(F.col("n") >= F.lit(ratio) * F.col("pages"))
    return often.groupBy(F.col("_host").alias("host")).agg(F.collect_set("line").alias("_often"))


def line_hash(line: Column) -> Column:
    """96 bits of a line, in two numbers."""
    return F.struct(F.xxhash64(line).alias("a"), F.hash(line).alias("b"))


def drop_repeated(pages: DataFrame, key: str = "page_id", url: str = "url", html: str = "html", ratio: float = RATIO, least_pages: int = LEAST_PAGES, scratch: Scratch | None = None) -> DataFrame:
    """(key, host, n_lines, n_dropped, kept_text) for each row of pages.

    A page is a row; a line counts once a page.  Pages without a host are one
    site.  A page without text has no lines and an empty kept_text.  Markup is
    read once: the lines are written to the shared folder, then counted and filtered.
    """
    scratch = scratch or Scratch(pages.sparkSession, "lines")
    own = scratch.table(pages.select(F.col(key).alias(key), host_of(F.col(url)).alias("_host"), lines_of(F.col(html)).alias("_lines")))
    often = scratch.table(repeated_lines(own, ratio, least_pages))
    often = if_small(often, LINES_BROADCAST // 100)
    joined = own.join(often, own["_host"] == often["host"], "left")
    kept = F.when(F.col("_often").isNull(), F.col("_lines")).otherwise(F.filter("_lines", lambda x: ~F.array_contains("_often", line_hash(x))))
    done = joined.withColumn("_kept", kept)
    return done.select(key, F.col("_host").alias("host"), F.size("_lines").alias("n_lines"), (F.size("_lines") - F.size("_kept")).alias("n_dropped"), F.array_join("_kept", "\n").alias("kept_text"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages without the lines that three tenths of their host's pages repeat."""
    return drop_repeated(table(spark, sf_dir, "pages"))


def _sql() -> str:
    text = "coalesce(html, '')"
    for pattern, to in ((HIDDEN, "' '"), (BREAKING, "chr(10)"), (TAG, "''")):
        text = f"regexp_replace({text}, '{pattern}', {to}, 'g')"
    for name, char in NAMED.items():
        text = f"replace({text}, '{name}', '{char.replace(chr(39), chr(39) * 2)}')".replace("'&#39;'", "'&#39;'")
    return f"""
WITH p AS (
  SELECT row_number() OVER () AS r, page_id, lower(regexp_extract(coalesce(url, ''), '{HOST}', 1)) AS host,
    list_filter(list_transform(regexp_split_to_array(regexp_replace({text}, '{BLANK}', ' ', 'g'), '{PARTED}'), lambda x: trim(x, ' ')), lambda x: x <> '') AS lines
  FROM pages
), each AS (SELECT r, host, unnest(list_distinct(lines)) AS line FROM p
), total AS (SELECT host, count(*) AS pages FROM p GROUP BY host
), often AS (
  SELECT host, line FROM each JOIN total USING (host) GROUP BY host, line, pages HAVING count(*) >= {LEAST_PAGES} AND count(*) >= {RATIO}::DOUBLE * pages
), lists AS (SELECT host, list(line) AS often FROM often GROUP BY host
), done AS (
  SELECT page_id, p.host, lines, list_filter(lines, lambda x: NOT list_contains(coalesce(often, []), x)) AS kept FROM p LEFT JOIN lists ON p.host = lists.host
)
SELECT page_id, host, len(lines)::INTEGER AS n_lines, (len(lines) - len(kept))::INTEGER AS n_dropped, coalesce(array_to_string(kept, chr(10)), '') AS kept_text FROM done
"""


ORACLE = _sql()
