"""Functions for SQL text: ``digest_agg(value)``, ``digest_rows(vals)``, ``logit(p)``."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, udtf

from ..operators.digest import Scheme
from ..operators.leaf import digest_agg


@arrow_udf("double")
def logit(p: pa.Array) -> pa.Array:
    """Log odds; null outside (0, 1)."""
    inside = pc.and_(pc.greater(p, 0.0), pc.less(p, 1.0))
    safe = pc.if_else(inside, p, 0.5)
    return pc.if_else(inside, pc.ln(pc.divide(safe, pc.subtract(1.0, safe))), pa.scalar(None, pa.float64()))


@udtf(returnType="i int, value double")
class DigestRows:
    def eval(self, vals):
        for i, v in enumerate(vals or []):
            yield i, v


def register(spark: SparkSession, scheme: Scheme = Scheme(batch=100)) -> None:
    spark.udf.register("digest_agg", digest_agg(scheme))
    spark.udf.register("logit", logit)
    spark.udtf.register("digest_rows", DigestRows)
