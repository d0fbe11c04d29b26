"""Edge-labelled graphs as DataFrames."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from regpath.functions.regex import Automaton, Step
from regpath.operators.scratch import Scratch


@dataclass(frozen=True)
class LabeledGraph:
    """A set of edges (src, label, dst).

    A further column `part`, if the edges have it, is a value that both ends of
    every edge share, of which each is small enough for a task: a user's
    timeline, a conversation.  guards: named sets of vertices (v).
    """

    edges: DataFrame
    guards: dict[str, DataFrame] = field(default_factory=dict)
    closed: bool = False

    @staticmethod
    def from_edges(df: DataFrame, src: str = "src", label: str = "label", dst: str = "dst", part: Column | None = None) -> LabeledGraph:
        """Edges without repetitions; rows with a null end or label are left out."""
        columns = [F.col(src).alias("src"), F.col(label).cast("string").alias("label"), F.col(dst).alias("dst")]
        made = df.select(*columns, *([part.alias("part")] if part is not None else []))
        return LabeledGraph(made.where("src is not null and label is not null and dst is not null").distinct())

    @staticmethod
    def from_triples(spark: SparkSession, path: str, separator: str = r"\s+") -> LabeledGraph:
        """Text lines of source, label and target; lines of another form are left out."""
        parts = spark.read.text(path).select(F.split(F.trim("value"), separator).alias("p")).where(F.size("p") == 3)
        return LabeledGraph.from_edges(parts.select(F.col("p")[0].alias("src"), F.col("p")[1].alias("label"), F.col("p")[2].alias("dst")))

    @staticmethod
    def from_files(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, src: str = "src", label: str = "label", dst: str = "dst", **options) -> LabeledGraph:
        """Edges from Parquet, ORC, JSON or CSV files; the latter two need a schema."""
        if schema is None and fmt in ("csv", "json"):
            raise ValueError(f"{fmt} files need a schema")
        reader = spark.read.format(fmt).options(**options)
        return LabeledGraph.from_edges((reader.schema(schema) if schema else reader).load(path), src, label, dst)

    @property
    def parted(self) -> bool:
        return "part" in self.edges.columns

    @property
    def vertex_type(self):
        return self.edges.schema["src"].dataType

    def vertices(self) -> DataFrame:
        """(v): ends of edges; with `part` if the edges have it."""
        more = ["part"] if self.parted else []
        return self.edges.select(F.col("src").alias("v"), *more).union(self.edges.select(F.col("dst").alias("v"), *more)).distinct()

    def symmetric(self, materialise: bool = False) -> LabeledGraph:
        """With inverse steps: by a flag of the automaton (nothing to do), or as edges labelled ^label both ways."""
        if not materialise:
            return self
        back = self.edges.withColumns({"src": F.col("dst"), "dst": F.col("src"), "label": F.concat(F.lit("^"), F.col("label"))})
        return replace(self, edges=self.edges.unionByName(back), closed=True)

    def with_guard(self, name: str, vertices: DataFrame) -> LabeledGraph:
        return replace(self, guards={**self.guards, name: vertices})

    def restrict(self, labels) -> LabeledGraph:
        """Edges of the given labels; a filter that reaches the scan.  None: all."""
        return self if labels is None else replace(self, edges=self.edges.where(F.col("label").isin(sorted(labels)) if labels else F.lit(False)))

    def stored(self, scratch: Scratch) -> LabeledGraph:
        """The same graph, its edges written to the shared folder once."""
        return replace(self, edges=scratch.table(self.edges))

    def save(self, path: str, inverse: bool = True) -> None:
        """Writes edges partitioned by label and sorted by src; a second copy sorted by dst serves inverse steps."""
        for name, end in (("by_src", "src"), ("by_dst", "dst"))[: 2 if inverse else 1]:
            self.edges.repartition("label", end).sortWithinPartitions("label", end).write.mode("overwrite").partitionBy("label").parquet(f"{path}/{name}")

    @staticmethod
    def load(spark: SparkSession, path: str) -> LabeledGraph:
        return LabeledGraph(spark.read.parquet(f"{path}/by_src").withColumn("label", F.col("label").cast("string")))

    def stats(self, approx: bool = False) -> dict[str, int]:
        """Numbers of vertices and edges; approx estimates the former."""
        ends = self.edges.select(F.explode(F.array("src", "dst")).alias("v"))
        count = F.approx_count_distinct("v") if approx else F.count_distinct("v")
        return {"vertices": ends.agg(count).first()[0], "edges": self.edges.count()}

    def label_stats(self) -> DataFrame:
        return self.edges.groupBy("label").agg(F.count(F.lit(1)).alias("edges"), F.count_distinct("src").alias("sources"), F.count_distinct("dst").alias("targets"))

    def takes(self, step: Step) -> Column:
        """Whether an edge's label fits a step."""
        if self.closed:
            names = sorted(("^" if step.inverse else "") + n for n in step.labels)
            inside = F.col("label").startswith("^") == F.lit(step.inverse)
        else:
            names, inside = sorted(step.labels), F.lit(True)
        listed = F.col("label").isin(names) if names else F.lit(False)
        return inside & ~listed if step.negated else listed

    def walked(self, step: Step) -> DataFrame:
        """(u, v) of the edges of a step, in the direction of the walk."""
        kept = self.edges.where(self.takes(step))
        a, b = ("dst", "src") if step.inverse and not self.closed else ("src", "dst")
        return kept.select(F.col(a).alias("u"), F.col(b).alias("v"))

    def step_relation(self, automaton: Automaton) -> DataFrame:
        """(u, q, v, p), with `part` if there is one: each edge or guard vertex under each transition that takes it.

        One scan of the edges that some letter takes; transitions stand in the
        plan as a short array, so nothing is joined.
        """
        by_letter: dict = {}
        for q, letter, p in automaton.transitions:
            by_letter.setdefault(letter, []).append((q, p))
        steps = [x for x in by_letter if isinstance(x, Step)]
        more = ["part"] if self.parted else []
        out = None
        if steps:
            moves = []
            for s in steps:
                back = s.inverse and not self.closed
                pairs = F.array(*[F.struct(F.lit(q).alias("q"), F.lit(p).alias("p"), F.lit(back).alias("back")) for q, p in by_letter[s]])
                moves.append(F.when(self.takes(s), pairs).otherwise(F.array().cast("array<struct<q:int,p:int,back:boolean>>")))
            any_of = self.takes(steps[0])
            for s in steps[1:]:
                any_of = any_of | self.takes(s)
            moved = self.edges.where(any_of).withColumn("m", F.explode(F.flatten(F.array(*moves))))
            out = moved.select(F.when(F.col("m.back"), F.col("dst")).otherwise(F.col("src")).alias("u"), F.col("m.q").alias("q"), F.when(F.col("m.back"), F.col("src")).otherwise(F.col("dst")).alias("v"), F.col("m.p").alias("p"), *more)
        for letter, pairs in by_letter.items():
            if not isinstance(letter, Step):
                held = self.guards[letter.name].select("v")
                held = self.vertices().join(held, "v", "left_semi") if self.parted else held
                pairs = F.explode(F.array(*[F.struct(F.lit(q).alias("q"), F.lit(p).alias("p")) for q, p in pairs]))
                stay = held.withColumn("m", pairs).select(F.col("v").alias("u"), F.col("m.q").alias("q"), "v", F.col("m.p").alias("p"), *more)
                out = stay if out is None else out.union(stay)
        if out is None:
            out = self.edges.where(F.lit(False)).select(F.col("src").alias("u"), F.lit(0).alias("q"), F.col("dst").alias("v"), F.lit(0).alias("p"), *more)
        return out
