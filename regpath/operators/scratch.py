"""Tables written to the folder that all executors share, to cut lineage.

The folder is the one the cluster names in ``spark.checkpoint.dir``.  Only in a
local session without that setting (tests) is a folder of our own made.
"""

from __future__ import annotations

import itertools
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The shared folder of this session."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        _OWN[app] = "file://" + tempfile.mkdtemp(prefix="regpath-")
    return _OWN[app]


class Scratch:
    """Written tables of one evaluation; those no longer read can be dropped."""

    def __init__(self, spark: SparkSession, name: str = "scratch") -> None:
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"
        self._n = itertools.count(1)  # tables may be written from several threads

    def table(self, df: DataFrame) -> DataFrame:
        """Writes df and reads it back: its lineage is the written files."""
        return self.spark.read.schema(df.schema).parquet(self.path(df))

    def path(self, df: DataFrame) -> str:
        path = f"{self.root}/{next(self._n):04d}"
        df.write.mode("overwrite").parquet(path)
        return path

    def drop(self, df: DataFrame | None) -> None:
        """Deletes the files of a table made by `table`; nothing may read it later."""
        if df is None:
            return
        for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            if self.root.split("://")[-1].lstrip("/") in name:
                path = self.spark._jvm.org.apache.hadoop.fs.Path(name)
                path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
