"""Graphs over the given tables."""

from __future__ import annotations

from collections.abc import Callable
import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from regpath.sources.graph import LabeledGraph


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def consecutive_edges(rows: DataFrame, key: list[str], order: list[str], vertex: Column, label: Column, where: Column | None = None, part: Column | None = None) -> LabeledGraph:
    """An edge from each row of a key to the next in order, labelled by the later row; `where` tests the later row."""
    w = Window.partitionBy(*key).orderBy(*order)
    made = rows.select(F.lag(vertex).over(w).alias("src"), label.alias("label"), vertex.alias("dst"), (F.lit(True) if where is None else where).alias("_on"), *([part.alias("_part")] if part is not None else []))
    return LabeledGraph.from_edges(made.where("_on"), part=F.col("_part") if part is not None else None)


def timeline(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Each user's events, one after the other; a user is a part."""
    events = read(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    return consecutive_edges(events, ["user_id"], ["ts", "event_id"], F.col("event_id"), F.col("event_type"), part=F.col("user_id"))


def item(props: Column) -> Column:
    return F.get_json_object(props, "$.k").cast("long")


def hop(spark: SparkSession, sf_dir: str, least: float = 95.0) -> LabeledGraph:
    """From item to item of a user's consecutive events, if the later one's value is large; with cycles."""
    events = read(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", item(F.col("props")).alias("k"))
    return consecutive_edges(events, ["user_id"], ["ts", "event_id"], F.col("k"), F.col("event_type"), where=F.col("value") >= least)


def talk(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Turns of a conversation, one after the other; a conversation is a part."""
    turns = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    return consecutive_edges(turns, ["conv_id"], ["turn"], F.col("conv_id") * 1000 + F.col("turn"), F.col("role"), part=F.col("conv_id"))


def _id(letter: str, key: str) -> Column:
    return F.concat(F.lit(letter), F.col(key).cast("string"))


def supply(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Customers, orders, parts, suppliers, nations and regions, by their keys."""
    t = {n: read(spark, sf_dir, n) for n in ("customer", "orders", "lineitem", "supplier", "nation")}

    def edges(table: str, src: Column, label: Column, dst: Column) -> DataFrame:
        return t[table].select(src.alias("src"), label.alias("label"), dst.alias("dst"))

    made = [
        edges("orders", _id("C", "o_custkey"), F.lit("placed"), _id("O", "o_orderkey")),
        edges("lineitem", _id("O", "l_orderkey"), F.concat(F.lit("contains_"), "l_returnflag"), _id("P", "l_partkey")),
        edges("lineitem", _id("P", "l_partkey"), F.lit("supplied_by"), _id("S", "l_suppkey")),
        edges("customer", _id("C", "c_custkey"), F.lit("c_in"), _id("N", "c_nationkey")),
        edges("supplier", _id("S", "s_suppkey"), F.lit("s_in"), _id("N", "s_nationkey")),
        edges("nation", _id("N", "n_nationkey"), F.lit("part_of"), _id("R", "n_regionkey")),
    ]
    out = made[0]
    for m in made[1:]:
        out = out.union(m)
    return LabeledGraph.from_edges(out)


def hrefs(html: Column) -> Column:
    return F.regexp_extract_all(html, F.lit('<a[^>]*href="([^"]*)"'), F.lit(1))


def web(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Pages, the addresses that their anchors lead to, and their hosts."""
    pages = read(spark, sf_dir, "pages")
    links = pages.select(_id("p", "page_id").alias("src"), F.lit("links").alias("label"), F.explode(hrefs(F.col("html"))).alias("dst"))
    hosts = pages.select(_id("p", "page_id").alias("src"), F.lit("on_host").alias("label"), F.concat(F.lit("h:"), F.parse_url("url", F.lit("HOST"))).alias("dst"))
    return LabeledGraph.from_edges(links.union(hosts))


def docs(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Documents with language, source, rating, text, and the benchmark passages that they hold."""
    d, rated, b = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"), read(spark, sf_dir, "benchmark")
    me = _id("d", "doc_id").alias("src")
    out = d.select(me, F.lit("in_lang").alias("label"), F.concat(F.lit("l:"), "lang").alias("dst"))
    out = out.union(d.select(me, F.lit("from_source"), F.concat(F.lit("s:"), "source"))).union(d.select(me, F.lit("has_text"), F.concat(F.lit("t:"), F.md5("text"))))
    out = out.union(rated.select(me, F.lit("rated"), F.concat(F.lit("q:"), F.col("quality").cast("string")))).union(quotes(d, b))
    return LabeledGraph.from_edges(out)


def quotes(d: DataFrame, b: DataFrame, words: int = 6) -> DataFrame:
    """(src, label, dst) of documents that hold a passage to the letter.

    The passage's first words, hashed, are looked up at each place of a text; a hit is checked as a whole.
    """
    head = b.select("item_id", F.col("text").alias("passage"), F.split("text", " ").alias("w")).where(F.size("w") >= words)
    head = head.select("item_id", "passage", F.xxhash64(*[F.col("w")[i] for i in range(1, words - 1)]).alias("seed"))
    at = d.select("doc_id", "text", F.split("text", " ").alias("w")).where(F.size("w") >= words)
    at = at.select("doc_id", "text", "w", F.explode(F.sequence(F.lit(1), F.size("w") - words + 2)).alias("i"))
    at = at.select("doc_id", "text", F.xxhash64(*[F.col("w")[F.col("i") + k] for k in range(words - 2)]).alias("seed"))
    hit = at.join(head, "seed").where(F.col("text").contains(F.col("passage")))
    return hit.select(_id("d", "doc_id").alias("src"), F.lit("quotes").alias("label"), _id("b", "item_id").alias("dst")).distinct()


def near(spark: SparkSession, sf_dir: str, k: int = 5, block: int = 2_000) -> LabeledGraph:
    """Each vector's k nearest by cosine, ties by vec_id; labelled by whether both have one label.

    Blocks of vectors are compared two by two; each gives its k best, of which the k best remain.
    """
    v = read(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label").where("embedding is not null")
    blocks = max(1, -(-v.count() // block))
    v = v.withColumn("own", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    rows = v.withColumn("other", other).select(F.col("own").alias("i"), F.col("other").alias("j"), F.lit(True).alias("asks"), "vec_id", "embedding", "label")
    rows = rows.union(v.withColumn("other", other).select(F.col("other"), F.col("own"), F.lit(False), "vec_id", "embedding", "label"))

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        q, c = pdf[pdf.asks], pdf[~pdf.asks].sort_values("vec_id")
        if not len(q) or not len(c):
            return pd.DataFrame({"src": [], "dst": [], "cosine": [], "same": []})
        a, b = (np.stack(x.embedding.to_numpy()).astype(np.float64) for x in (q, c))
        s = (a / np.linalg.norm(a, axis=1, keepdims=True)) @ (b / np.linalg.norm(b, axis=1, keepdims=True)).T
        s[q.vec_id.to_numpy()[:, None] == c.vec_id.to_numpy()[None, :]] = -2
        top = np.argsort(-s, axis=1, kind="stable")[:, :k]
        src, dst = np.repeat(q.vec_id.to_numpy(), top.shape[1]), c.vec_id.to_numpy()[top].reshape(-1)
        same = np.repeat(q.label.to_numpy(), top.shape[1]) == c.label.to_numpy()[top].reshape(-1)
        out = pd.DataFrame({"src": src, "dst": dst, "cosine": np.take_along_axis(s, top, 1).reshape(-1), "same": same})
        return out[out.cosine > -2]

    found = rows.groupBy("i", "j").applyInPandas(best, "src long, dst long, cosine double, same boolean")
    ranked = found.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cosine"), "dst"))).where(F.col("r") <= k)
    return LabeledGraph.from_edges(ranked.select("src", F.when(F.col("same"), "same").otherwise("diff").alias("label"), "dst"))


GRAPHS = {"timeline": timeline, "hop": hop, "supply": supply, "talk": talk, "web": web, "docs": docs, "near": near}


def graph_from_tables(spark: SparkSession, sf_dir: str, name: str) -> LabeledGraph:
    return GRAPHS[name](spark, sf_dir)


# ---- made graphs


def chain(spark: SparkSession, n: int, label: str = "a") -> LabeledGraph:
    return LabeledGraph.from_edges(spark.range(n).select(F.col("id").alias("src"), F.lit(label).alias("label"), (F.col("id") + 1).alias("dst")))


def cycle(spark: SparkSession, n: int, label: str = "a") -> LabeledGraph:
    return LabeledGraph.from_edges(spark.range(n).select(F.col("id").alias("src"), F.lit(label).alias("label"), ((F.col("id") + 1) % n).alias("dst")))


def complete(spark: SparkSession, n: int, label: str = "a") -> LabeledGraph:
    both = spark.range(n * n).select((F.col("id") % n).alias("src"), F.floor(F.col("id") / n).alias("dst")).where("src != dst")
    return LabeledGraph.from_edges(both.select("src", F.lit(label).alias("label"), "dst"))


def fan_in_out(spark: SparkSession, p: int, q: int, label: str = "a") -> LabeledGraph:
    """p vertices into one, and q out of it: p * q pairs two steps apart over p + q edges."""
    i = spark.range(p).select((F.col("id") + 1).alias("src"), F.lit(label).alias("label"), F.lit(0).cast("long").alias("dst"))
    o = spark.range(q).select(F.lit(0).cast("long").alias("src"), F.lit(label).alias("label"), (F.col("id") + 1 + p).alias("dst"))
    return LabeledGraph.from_edges(i.union(o))


def comb(spark: SparkSession, h: int, t: int, label: str = "a") -> LabeledGraph:
    """A chain of h vertices, each with a chain of t teeth."""
    spine = spark.range(h - 1).select((F.col("id") * (t + 1)).alias("src"), F.lit(label).alias("label"), ((F.col("id") + 1) * (t + 1)).alias("dst"))
    teeth = spark.range(h * t).select((F.floor(F.col("id") / t) * (t + 1) + F.col("id") % t).alias("src"), F.lit(label).alias("label"), (F.floor(F.col("id") / t) * (t + 1) + F.col("id") % t + 1).alias("dst"))
    return LabeledGraph.from_edges(spine.union(teeth))


# ---- edges by time


def seconds_of(ts: str) -> Column:
    """A time as seconds since 1970, whatever the session's time zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', CAST(`{ts}` AS TIMESTAMP_NTZ))") / 1e6


def edges_asof(left: DataFrame, right: DataFrame, key: list[str], left_ts: str, right_ts: str, left_id: str, right_id: str, label: str, tie: str) -> LabeledGraph:
    """From each left row to the last right row of its key at or before it; of equal times the greatest `tie`."""
    a = left.select(*key, F.col(left_ts).alias("_t"), F.lit(1).alias("_kind"), F.col(left_id).alias("_l"), F.lit(None).cast(right.schema[right_id].dataType).alias("_r"), F.lit(None).cast("long").alias("_tie"))
    b = right.select(*key, F.col(right_ts).alias("_t"), F.lit(0).alias("_kind"), F.lit(None).cast(left.schema[left_id].dataType).alias("_l"), F.col(right_id).alias("_r"), F.col(tie).cast("long").alias("_tie"))
    w = Window.partitionBy(*key).orderBy("_t", "_kind", "_tie").rowsBetween(Window.unboundedPreceding, 0)
    last = a.unionByName(b).withColumn("_last", F.last("_r", ignorenulls=True).over(w)).where("_kind = 1 and _last is not null")
    return LabeledGraph.from_edges(last.select(F.col("_l").alias("src"), F.lit(label).alias("label"), F.col("_last").alias("dst")))


def edges_range_join(rows: DataFrame, key: list[str], ts: str, vertex: str, seconds: int, label: str) -> LabeledGraph:
    """From each row to the later ones of its key within so many seconds.

    Time is cut into spans of that length, so the range becomes an equality of
    span or next span: no task compares rows far apart.
    """
    t = seconds_of(ts)
    a = rows.select(*key, t.alias("_t"), F.col(vertex).alias("src"), F.explode(F.array(F.floor(t / seconds), F.floor(t / seconds) + 1)).alias("_span"))
    b = rows.select(*key, t.alias("_u"), F.col(vertex).alias("dst"), F.floor(t / seconds).alias("_span"))
    met = a.join(b, [*key, "_span"]).where((F.col("_u") > F.col("_t")) & (F.col("_u") - F.col("_t") <= seconds))
    return LabeledGraph.from_edges(met.select("src", F.lit(label).alias("label"), "dst"))


def edges_interval(spans: DataFrame, points: DataFrame, key: list[str], start: str, vertex: str, ts: str, target: str, seconds: int, label: str) -> LabeledGraph:
    """From each row of `spans` to the points of its key that fall in [start, start + seconds).

    A span lies in two cells of that length at most, a point in one: cells make the interval an equality.
    """
    t, u = seconds_of(start), seconds_of(ts)
    a = spans.select(*key, t.alias("_t"), F.col(vertex).alias("src"), F.explode(F.array(F.floor(t / seconds), F.floor(t / seconds) + 1)).alias("_cell"))
    b = points.select(*key, u.alias("_u"), F.col(target).alias("dst"), F.floor(u / seconds).alias("_cell"))
    met = a.join(b, [*key, "_cell"]).where((F.col("_u") >= F.col("_t")) & (F.col("_u") < F.col("_t") + seconds))
    return LabeledGraph.from_edges(met.select("src", F.lit(label).alias("label"), "dst"))


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays, in double precision, without Python."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def cosine_edges(spark: SparkSession, sf_dir: str, k: int = 5, by: Callable[[Column, Column], Column] | None = None) -> DataFrame:
    """(src, label, dst, cosine): nearest neighbours with their cosine, recomputed from the vectors; by: another function for it."""
    g, v = near(spark, sf_dir, k).edges, read(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    both = g.join(v.select(F.col("vec_id").alias("src"), F.col("embedding").alias("_a")), "src").join(v.select(F.col("vec_id").alias("dst"), F.col("embedding").alias("_b")), "dst")
    return both.select("src", "label", "dst", F.round((by or cosine)(F.col("_a"), F.col("_b")), 4).alias("cosine"))


def session_edges(rows: DataFrame, key: list[str], ts: str, vertex: str, tie: str, gap: str, label: str = "same_session") -> LabeledGraph:
    """From each row to the next of its session, which a gap ends."""
    w = Window.partitionBy(*key).orderBy(ts, tie)
    seconds = seconds_of(ts) - F.lag(seconds_of(ts)).over(w)
    made = rows.select(F.lag(vertex).over(w).alias("src"), F.lit(label).alias("label"), F.col(vertex).alias("dst"), (seconds < _seconds(gap)).alias("_on"))
    return LabeledGraph.from_edges(made.where("_on"))


def _seconds(gap: str) -> int:
    n, unit = gap.split()
    return int(n) * {"second": 1, "minute": 60, "hour": 3600, "day": 86400}[unit.rstrip("s")]
