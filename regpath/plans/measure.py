"""What a run cost: time, stages, shuffled and spilled bytes, from Spark's own status store."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def _stages(spark: SparkSession) -> dict[tuple[int, int], tuple[int, int, int, int]]:
    """(stage, attempt): tasks, shuffle bytes written, bytes spilled, records shuffled."""
    sc = spark.sparkContext
    none = sc._gateway.new_array(sc._jvm.double, 0)
    found = sc._jsc.sc().statusStore().stageList(None, False, False, none, sc._jvm.java.util.ArrayList())
    out = {}
    for i in range(found.size()):
        s = found.apply(i)
        out[s.stageId(), s.attemptId()] = (s.numCompleteTasks(), s.shuffleWriteBytes(), s.diskBytesSpilled(), s.shuffleWriteRecords())
    return out


def measured(spark: SparkSession, run: Callable[[], DataFrame]) -> dict[str, float]:
    """Rows, seconds and work of one evaluation, the counting of its result included."""
    before, began = set(_stages(spark)), time.perf_counter()
    rows = run().count()
    seconds = time.perf_counter() - began
    new = [v for k, v in _stages(spark).items() if k not in before]
    return {"rows": rows, "seconds": round(seconds, 3), "stages": len(new), "tasks": sum(v[0] for v in new), "shuffle_bytes": sum(v[1] for v in new), "spill_bytes": sum(v[2] for v in new), "shuffle_rows": sum(v[3] for v in new)}


def compared(spark: SparkSession, runs: dict[str, Callable[[], DataFrame]]) -> DataFrame:
    """One row for each named evaluation."""
    rows = []
    for name, run in runs.items():
        m = measured(spark, run)
        rows.append((name, m["rows"], m["seconds"], m["stages"], m["tasks"], m["shuffle_bytes"], m["spill_bytes"], m["shuffle_rows"]))
    return spark.createDataFrame(rows, "name string, rows long, seconds double, stages int, tasks long, shuffle_bytes long, spill_bytes long, shuffle_rows long")
