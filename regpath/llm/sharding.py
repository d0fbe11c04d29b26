"""Sharding by a weighted hash tree of regions, racks and shards."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.llm.common import table
from regpath.operators.scratch import Scratch

#: Rows of a shard are numbered bucket by bucket; so many leading bits of their hash name the bucket.
SLOT_BITS = 12


@dataclass(frozen=True)
class Node:
    """A region, rack or shard; a shard has a number and a weight, others have children."""

    name: str
    children: tuple[Node, ...] = field(default=())
    shard: int | None = None
    own: float = 1.0

    @property
    def weight(self) -> float:
        return sum(c.weight for c in self.children) if self.children else self.own


def tree_of(shards: int, region: int = 8, rack: int = 4) -> Node:
    """Regions of 8 shards, each of two racks of four; the last of each kind may hold fewer."""
    rows = [Node(f"s{s}", shard=s) for s in range(shards)]
    racks = [Node(f"k{k}", tuple(rows[k * rack : (k + 1) * rack])) for k in range(-(-shards // rack))]
    a = region // rack
    return Node("all", tuple(Node(f"r{r}", tuple(racks[r * a : (r + 1) * a])) for r in range(-(-shards // region))))


def with_region(tree: Node, shards: int, name: str) -> Node:
    """The tree with one more region of one rack of new shards.

    No weight inside the other regions changes, so a row either goes to the new
    region or stays in its shard.
    """
    first = 1 + max(_numbers(tree))
    rack = Node(f"{name}k", tuple(Node(f"s{first + i}", shard=first + i) for i in range(shards)))
    return Node(tree.name, (*tree.children, Node(name, (rack,))))


def _numbers(node: Node) -> list[int]:
    return [node.shard] if node.shard is not None else [n for c in node.children for n in _numbers(c)]


def _draw(hashed: Column, name: str) -> Column:
    """A number in (0, 1] of a node, fixed by its name and a key's hash: 53 bits of a 64-bit hash."""
    return (F.shiftrightunsigned(F.xxhash64(F.lit(name), hashed), 11) + F.lit(1)).cast("double") * F.lit(2.0**-53)


def _shard_of(hashed: str, tree: Node) -> Column:
    """The shard of a key's hash: level by level the child with the greatest ln(draw) / weight; ties go to the last."""
    if tree.shard is not None:
        return F.lit(tree.shard)
    children = [c for c in tree.children if c.weight > 0]
    if len(children) == 1:
        return _shard_of(hashed, children[0])
    scores = [F.struct((F.log(_draw(F.col(hashed), c.name)) / F.lit(float(c.weight))).alias("score"), F.lit(i).alias("i")) for i, c in enumerate(children)]
    best = F.array_max(F.array(*scores))["i"]
    if all(c.shard is not None for c in children):
        return F.array(*[F.lit(c.shard) for c in children])[best]
    # the choice is bound to a name once: were it an expression of each branch, every branch would draw again
    found = F.transform(F.array(best), lambda at: F.coalesce(*[F.when(at == i, _shard_of(hashed, c)) for i, c in enumerate(children)]))
    return found[0]


def with_shard(rows: DataFrame, key: str, tree: Node, out: str = "shard", seed: str = "shard") -> DataFrame:
    """Adds the shard of each key: at each level the child with the greatest ln(draw) / weight.

    A child's draw depends on the key and its name alone.  A change of weight
    moves rows only to or from the subtrees whose weight changes.  Children of
    weight 0 get nothing.  Null keys are one key.  A key is hashed once, and only the
    children on its way draw.
    """
    if tree.weight <= 0:
        raise ValueError(f"{tree.name} has no weight")
    names, hashed = rows.columns, "_hash_" + "_".join(rows.columns)
    keyed = rows.withColumn(hashed, F.xxhash64(F.lit(seed), F.coalesce(F.col(f"`{key}`").cast("string"), F.lit(""))))
    return keyed.select(*[F.col(f"`{c}`") for c in names], _shard_of(hashed, tree).cast("int").alias(out))


def with_slots(rows: DataFrame, shard: str, key: list[str], slot: str = "slot", scratch: Scratch | None = None) -> DataFrame:
    """Numbers the rows of each shard from 0 without a gap, in the order of a hash of their key.

    Equal rows are first counted into one, and get adjacent numbers; what is left
    is written, as it is read twice.  Each
    shard is cut by its hash into 2^SLOT_BITS buckets that are numbered on their
    own, from the count of the buckets before: no task holds a whole shard.
    """
    scratch, names = scratch or Scratch(rows.sparkSession, "slots"), rows.columns
    places = [f"c{i}" for i in range(len(names))]
    order = [places[names.index(k)] for k in key]
    counted = rows.toDF(*places).groupBy(*places).agg(F.count(F.lit(1)).alias("n"))
    counted = scratch.table(counted.withColumn("h", F.xxhash64(*[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in order])))
    counted = counted.withColumn("s", F.col(places[names.index(shard)])).withColumn("b", F.shiftrightunsigned("h", 64 - SLOT_BITS).cast("int"))
    sizes = counted.groupBy("s", "b").agg(F.sum("n").alias("rows"))
    before = "coalesce(sum(rows) over (partition by s order by b rows between unbounded preceding and 1 preceding), 0)"
    # at most shards * 2^SLOT_BITS rows, whatever the number of documents
    joined = counted.join(F.broadcast(sizes.select("s", "b", F.expr(before).alias("start"))), ["s", "b"])
    within = f"coalesce(sum(n) over (partition by s, b order by h, {', '.join(order + places)} rows between unbounded preceding and 1 preceding), 0)"
    numbered = joined.withColumn("at", F.col("start") + F.expr(within))
    numbered = numbered.select(*places, F.explode(F.sequence(F.col("at"), F.col("at") + F.col("n") - 1)).alias("slot"))
    return numbered.toDF(*names, slot)


def assign(docs: DataFrame, tree: Node, key: str = "doc_id", text: str = "text", grown: Node | None = None, seed: str = "shard", scratch: Scratch | None = None) -> DataFrame:
    """(key, size, text_crc32, law, shard, slot, grown_shard) for each row of docs.

    size: UTF-8 bytes of the text plus 1 (null text: 1).  Rows are reduced to these
    numbers before anything is shuffled.  Repeated rows keep their own slots.
    """
    body = F.coalesce(F.col(text), F.lit(""))
    rows = docs.select(F.col(key).alias("key"), (F.octet_length(body) + 1).cast("long").alias("size"), F.crc32(body.cast("binary")).cast("long").alias("crc"))
    rows = with_shard(rows, "key", tree, "shard", seed)
    rows = with_shard(rows, "key", grown, "grown", seed) if grown else rows.withColumn("grown", F.lit(None).cast("int"))
    numbered = with_slots(rows, "shard", ["key", "size", "crc"], scratch=scratch)
    return numbered.select(F.col("key").alias(key), "size", F.col("crc").alias("text_crc32"), F.lit("key").alias("law"), "shard", "slot", F.col("grown").alias("grown_shard"))


def op5_shard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 16 shards of two regions; grown_shard: with a region of one more shard."""
    tree = tree_of(16)
    return assign(table(spark, sf_dir, "documents"), tree, grown=with_region(tree, 1, "r2"))
