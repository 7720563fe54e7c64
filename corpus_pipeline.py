"""The corpus pipeline: quality filter, near-dedup, source mixing, byte-level BPE.

``STAGES`` are ``(name, function)``; a function takes ``(spark, docs, sf_dir)`` and returns a DataFrame, which
is written as Parquet and read again as the next stage's ``docs``.  In every stage extra columns of ``docs`` pass
through whatever their names (but for the last, which names its columns), and an empty table gives an empty table.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cdfblend.llm import byte_bpe, minhash_dedup, mixing, quality
from cdfblend.llm.workspace import Workspace, unused

#: The first stages are a fitted model and an iterative search, which SQL does not express; tests hold them to brute force.
ORACLE_SQL = None


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts (score >= 0.7); where no label can train it, all of them.

    Null and empty texts and null ids are scored like others; repeated rows have one fate.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    if labels.where("quality in (0, 1)").isEmpty():
        return docs
    model = quality.train(docs, labels)
    if not model.rows:  # all labels are held out, or of other documents
        return docs
    (score,) = unused(docs.columns, "score")
    return quality.score(docs, model, name=score).where(F.col(score) >= 0.7).select(*docs.columns)


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest id of every group of near copies (five-word shingles, similarity >= 0.8).

    Null and wordless texts have no copies; rows with a null id stay; rows that repeat an id share its fate.
    """
    groups = minhash_dedup.near_duplicates(docs, width=5, percent=80)
    (key,) = unused(docs.columns, "gone")
    gone = groups.where("doc_id is not null and not kept").select(F.col("doc_id").alias(key)).distinct()
    return docs.join(gone, F.col("doc_id") == F.col(key), "left_anti")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Weights 5, 2, 1 by source, at most three epochs; a row stands as often as the mix repeats it.

    Null sources are one source, last in order; null and empty texts have size 0 and come as often as their source's
    whole epochs say; rows that repeat an id share its fate.
    """
    return mixing.repeat_rows(docs, (5, 2, 1), 3.0)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every row: ``doc_id, source, lang, n_tokens, token_ids`` (little-endian unsigned 32-bit).

    Null and empty texts have no ids; a null id keeps its row; repeated rows are repeated.
    """
    ids = byte_bpe.encode_texts(docs.select("doc_id", "source", "lang", "text"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    return ids.select("doc_id", "source", "lang", (F.octet_length("token_ids") / 4).cast("long").alias("n_tokens"), "token_ids")


STAGES = [("quality", keep_good), ("near_dedup", keep_one_of_near_copies), ("mixing", mix_sources), ("byte_bpe", encode)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    ws = Workspace(spark, "pipeline")
    for name, stage in STAGES[:-1]:
        docs = ws.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
