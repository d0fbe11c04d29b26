from __future__ import annotations

from datetime import datetime, timedelta

from regpath.plans import evaluate as ev
from regpath.plans import workloads
from regpath.sources import builders
from regpath.streaming import feed
from tests.test_reach import got


def put(spark, path, rows, mode):
    spark.createDataFrame(rows, feed.EVENTS).coalesce(1).write.mode(mode).parquet(path)


def test_replay_with_duplicates_and_late_rows(spark, tmp_path):
    t = datetime(2024, 1, 1)
    rows = [(i, t + timedelta(minutes=i), i % 2, "view" if i % 3 else "click") for i in range(12)]
    source, graph = str(tmp_path / "in"), str(tmp_path / "graph")
    put(spark, source, rows[:6], "overwrite")
    for batch in (rows[4:9], [rows[2], *rows[9:]]):  # repeated and late rows come again
        feed.append_to_graph(feed.stream_edges(feed.stream_events(spark, source)), graph, str(tmp_path / "cp")).awaitTermination()
        put(spark, source, batch, "append")
    feed.append_to_graph(feed.stream_edges(feed.stream_events(spark, source)), graph, str(tmp_path / "cp")).awaitTermination()
    want = {(i, rows[i + 2][3], i + 2) for i in range(10)}
    assert got(feed.graph_of(spark, graph).edges.select("src", "label", "dst")) == want


def test_streamed_graph_gives_the_batch_result(spark, sf):
    from regpath.sources.graph import LabeledGraph

    q = workloads.workload("four_atoms")
    streamed = LabeledGraph(feed.replayed_timeline(spark, sf))
    assert got(ev.evaluate(q, streamed)) == got(ev.evaluate(q, builders.timeline(spark, sf)))


def test_windows(spark, tmp_path):
    t = datetime(2024, 1, 1)
    put(spark, str(tmp_path / "in"), [(1, t, 1, "view"), (1, t, 1, "view"), (2, t + timedelta(minutes=5), 1, "view"), (3, t + timedelta(hours=3), 1, "view")], "overwrite")
    for kind, size, slide, n in (("tumbling", "1 hour", None, 2), ("sliding", "2 hours", "1 hour", 4), ("session", "30 minutes", None, 2)):
        spans = feed.windowed(feed.stream_events(spark, str(tmp_path / "in")), kind, size, slide)
        name = f"windows_{kind}"
        grouped = spans.groupBy("user_id", "span").count()
        grouped.writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True).start().awaitTermination()
        assert spark.sql(f"SELECT * FROM {name}").count() == n, kind
    feed.deduplicated(feed.stream_events(spark, str(tmp_path / "in"))).writeStream.format("memory").queryName("once").trigger(availableNow=True).start().awaitTermination()
    assert spark.sql("SELECT * FROM once").count() == 3


def test_queries_over_closed_windows(spark, tmp_path):
    """Each closed window's result is that of a batch query over its events alone; the last window stays open."""
    from regpath.operators import reach
    from regpath.functions.regex import parse_path
    from regpath.sources.graph import LabeledGraph

    t = datetime(2024, 1, 1)
    rows = [(i, t + timedelta(hours=2 * i), i % 2, "view" if i % 3 else "click") for i in range(40)]
    put(spark, str(tmp_path / "in"), rows, "overwrite")
    query = lambda g: reach.pairs_capped(g, parse_path("view+"))
    feed.evaluated_windows(feed.stream_events(spark, str(tmp_path / "in")), query, str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination()
    found = {(r["window_start"].day, r["x"], r["y"]) for r in spark.read.parquet(str(tmp_path / "out" / "batch=*" / "start=*")).collect()}
    want = set()
    for day in (1, 2, 3):
        own = [r for r in rows if r[1].day == day]
        edges = [(a[0], b[3], b[0]) for u in (0, 1) for a, b in zip([r for r in own if r[2] == u], [r for r in own if r[2] == u][1:], strict=False)]
        want |= {(day, x, y) for x, y in got(query(LabeledGraph.from_edges(spark.createDataFrame(edges, "src long, label string, dst long"))))}
    assert found == want and {d for d, _, _ in found} == {1, 2, 3}


def test_late_events_are_counted_and_state_expires(spark, tmp_path):
    t = datetime(2024, 1, 1)
    rows = [(i, t + timedelta(minutes=i), 1, "view") for i in range(4)]
    source, graph = str(tmp_path / "in"), str(tmp_path / "graph")

    def step(batch):
        put(spark, source, batch, "append")
        feed.append_to_graph(feed.stream_edges(feed.stream_events(spark, source), 3_600_000), graph, str(tmp_path / "cp")).awaitTermination()

    step(rows[:3])
    step([rows[1], (90, t, 1, "view"), rows[3]])
    assert {tuple(r) for r in feed.late_events(spark, graph).collect()} == {(1, 2)}
    assert got(feed.graph_of(spark, graph).edges.select("src", "dst")) == {(0, 1), (1, 2), (2, 3)}
    step([(91, t + timedelta(days=2), 2, "view")])  # the watermark passes user 1's last event
    step([(4, t + timedelta(days=2), 1, "view"), (5, t + timedelta(days=2, minutes=1), 1, "view")])
    assert got(feed.graph_of(spark, graph).edges.select("src", "dst")) == {(0, 1), (1, 2), (2, 3), (4, 5)}
