"""Digest stores, format round trips and a simulated stream as a data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.digest import DIGEST_DDL, Scheme
from ..operators.leaf import summarize
from ..scratch import scratch
from .tables import ORDER, table

def write(digests: DataFrame, path: str, by: str = "day", keys: tuple[str, ...] = ("user_id",), mode: str = "append") -> None:
    """Partitioned by period, rows of a partition together and sorted by key."""
    digests.repartition(by).sortWithinPartitions(by, *keys).write.mode(mode).partitionBy(by).parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def write_and_read(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User-day digests through a partitioned store."""
    e = table(spark, sf_dir, "events").withColumn("day", F.to_date("ts"))
    path = scratch(spark)
    write(summarize(e, ["day", "user_id"], "value", ORDER["events"], Scheme()), path)
    return read(spark, path)


def facts(stored: DataFrame) -> DataFrame:
    return stored.select(F.col("day").cast("timestamp_ntz").alias("day"), "user_id", F.col("digest.n").alias("n"), F.array_min("digest.vals").alias("low"), F.array_max("digest.vals").alias("high"))


def roundtrip(df: DataFrame, fmt: str) -> DataFrame:
    path = scratch(df.sparkSession)
    options = {"header": "true"} if fmt == "csv" else {}
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).options(**options).schema(df.schema).load(path)


def through_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = summarize(table(spark, sf_dir, "events"), ["user_id"], "value", ORDER["events"], Scheme())
    back = d.select("user_id", F.from_json(F.to_json("digest"), DIGEST_DDL).alias("digest"))
    return back.select("user_id", F.col("digest.n").alias("n"), F.array_min("digest.vals").alias("low"), F.array_max("digest.vals").alias("high"))


class SimulatedStream(DataSource):
    """``leaf, seq, value``: log-normal streams with a leaf effect; options leaves, per_leaf, seed."""

    @classmethod
    def name(cls) -> str:
        return "simulated_stream"

    def schema(self) -> str:
        return "leaf long, seq long, value double"

    def reader(self, schema):
        return _Reader(self.options)


class _Part(InputPartition):
    def __init__(self, leaf: int):
        self.leaf = leaf


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.leaves, self.per_leaf, self.seed = int(options.get("leaves", 10)), int(options.get("per_leaf", 100)), int(options.get("seed", 1))

    def partitions(self):
        return [_Part(k) for k in range(self.leaves)]

    def read(self, part):
        import numpy as np

        rng = np.random.Generator(np.random.Philox(key=[self.seed, part.leaf]))
        for k, x in enumerate(np.exp(rng.normal(rng.normal(0, 0.2), 0.4, self.per_leaf))):
            yield (part.leaf, k, float(x))


def simulated(spark: SparkSession, leaves: int, per_leaf: int, seed: int) -> DataFrame:
    spark.dataSource.register(SimulatedStream)
    return spark.read.format("simulated_stream").option("leaves", leaves).option("per_leaf", per_leaf).option("seed", seed).load()
