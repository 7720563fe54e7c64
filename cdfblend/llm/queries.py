"""The thin ``opN_<name>`` queries over whole tables, and DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(fn: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    QUERIES[fn.__name__] = fn
    return fn


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@query
def op1_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links at cosine >= 0.98 within a label, over all rows of ``embeddings``."""
    from .embedding_dedup import link_vectors

    return link_vectors(table(spark, sf_dir, "embeddings"), threshold=0.98)


@query
def op2_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """4-word shingle sets at similarity >= 0.8, over all of ``documents``."""
    from .minhash_dedup import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"), width=4, percent=80)


@query
def op9_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights 5, 2, 1 by source, at most three epochs, over all of ``documents``."""
    from .mixing import mix

    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


@query
def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of every whole text by word_bpe_49k, through a cache that starts empty."""
    import public_tokenizers

    from .token_counts import count_tokens

    return count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), limit=2048)


@query
def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """byte_bpe_50k ids of every whole text, and what they decode to."""
    import public_tokenizers

    from .byte_bpe import encode_digests

    return encode_digests(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


@query
def op4_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Canonical digests of every whole text and of its edited text."""
    from .fingerprints import fingerprint

    return fingerprint(table(spark, sf_dir, "documents"))


@query
def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality of every whole text, learnt from the rows of ``labels`` that are not held out."""
    from .quality import classify

    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), threshold=0.7)


@query
def op10_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every whole page."""
    from pyspark.sql import functions as F

    from .html_extract import extract

    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return extract(pages).select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))


#: Production setting of the sharding query.
SHARDS = [f"shard-{k:03d}" for k in range(64)]


@query
def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Slot and shard of every document by its id, over 64 shards and 65,537 slots."""
    from .sharding import assign

    return assign(table(spark, sf_dir, "documents").select("doc_id"), "doc_id", SHARDS)


@query
def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The maximal conversations of ``conversations``, rendered."""
    from .chat import collapse

    return collapse(table(spark, sf_dir, "conversations"))


def _register_sql() -> None:
    from . import chat, embedding_dedup, minhash_dedup, mixing, sharding

    ORACLES.update({"op1_embedding_dedup": embedding_dedup.ORACLE, "op2_minhash_dedup": minhash_dedup.ORACLE, "op3_sharding": sharding.oracle(SHARDS), "op8_chat_format": chat.ORACLE, "op9_source_mixing": mixing.ORACLE})


_register_sql()
