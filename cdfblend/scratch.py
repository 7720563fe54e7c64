"""Fresh paths in the folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

_local: list[str] = []


def scratch(spark: SparkSession) -> str:
    """A path below ``spark.checkpoint.dir``; below a temporary folder where that is unset, which only local mode allows."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        if not _local:
            _local.append(tempfile.mkdtemp(prefix="cdfblend-store-"))
            atexit.register(shutil.rmtree, _local[0], True)
        root = f"file://{_local[0]}"
    return f"{root.rstrip('/')}/store-{uuid.uuid4().hex[:12]}"


_ONCE: dict[tuple, str] = {}


def once(spark: SparkSession, key: tuple, make: Callable[[], DataFrame]) -> DataFrame:
    """What ``make`` gives, computed and written by the first call of an application with this key, read by later ones."""
    at = (spark.sparkContext.applicationId, *key)
    if at not in _ONCE:
        path = scratch(spark)
        make().write.parquet(path)
        _ONCE[at] = path
    return spark.read.parquet(_ONCE[at])
