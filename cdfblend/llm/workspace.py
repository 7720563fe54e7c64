"""Intermediate tables in the folder that all executors share.

Lineage is cut by writing Parquet there and reading it back, so a lost executor costs a re-read and
never a recomputation of an iterative plan.  The folder is ``spark.checkpoint.dir``; only where that
is unset a temporary folder of this process is used, and only in local mode: elsewhere executors could not read it.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession

_fallback: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    if not _fallback:
        _fallback.append(tempfile.mkdtemp(prefix="cdfblend-"))
    return f"file://{_fallback[0]}"


class Workspace:
    """Tables of one operator run. ``drop`` frees one early; the rest goes when the process ends."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"
        self._n = 0
        atexit.register(self.drop_all)

    def path(self, name: str) -> str:
        self._n += 1
        return f"{self.root}/{self._n:03d}-{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        path = self.path(name)
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._workspace_path = path
        return out

    def drop(self, *tables: DataFrame | None) -> None:
        for t in tables:
            path = getattr(t, "_workspace_path", None)
            if path:
                _delete(self.spark, path)

    def drop_all(self) -> None:
        try:
            _delete(self.spark, self.root)
        except Exception:  # the session has ended before: nothing left to call
            pass


def _delete(spark: SparkSession, path: str) -> None:
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(conf).delete(p, True)


def unused(taken: Iterable[str], *names: str) -> list[str]:
    """The names, each with as many underscores appended as keep it apart (in any case) from the names in use."""
    used = {c.lower() for c in taken}
    out = []
    for name in names:
        while name.lower() in used:
            name += "_"
        used.add(name.lower())
        out.append(name)
    return out


def parallelism(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
