"""Token counts through a digest cache.

The key of a text is the SHA-256 of its normal form; the cache holds ``(tokenizer, key, n_tokens)``
rows, partitioned by the digest of the tokenizer's file, so another version never meets old counts.
One aggregate keeps one text per key (it combines before it shuffles, so thousands of copies travel
once per task); an anti-join with the cache leaves the misses; only these are encoded, and appended.
Counts then come from a join with the cache on the key, which adaptive execution can split.

The normal form folds ASCII case and runs of ASCII white space, which ``word_bpe`` vocabularies drop
anyway; a text that holds ``<|`` keeps its exact form, because special strings are matched before
normalisation.  For other tokenizers the normal form is the text itself.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .memory import tidy
from .workspace import Workspace

PIECE_CHARS = 1 << 20
MEMORY_WORDS = 500_000
#: Fixed value: the word pattern for which counts of words add up to the count of a text.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: White space as the tokenizers library's patterns have it, as the inside of a character class.
WHITE = "\\x09-\\x0d\\x20\\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
_BEYOND_LATIN = re.compile("[^\x00-\u024f]").search


class WordCounts:
    """Token counts as sums over words, for a tokenizer whose pre-tokenizer keeps words apart.

    Each distinct word is encoded once by the library and its count is kept (up to a bounded number of words).
    Latin texts need no normalisation but lower case.  Texts with other characters, and texts that hold ``<|``
    (special strings are matched first), go to the library whole.
    """

    def __init__(self, tokenizer, pattern: str):
        self.tokenizer = tokenizer
        self.pattern = regex.compile(pattern.replace("\\s", WHITE))
        self.memory: dict[str, int] = {}

    def whole(self, texts: list[str]) -> list[int]:
        return [len(e) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def __call__(self, texts: list[str]) -> list[int]:
        split = []
        for t in texts:
            split.append(None if "<|" in t or _BEYOND_LATIN(t) else self.pattern.findall(t.lower()))
        found = set().union(*[w for w in split if w])
        if len(self.memory) + len(found) > MEMORY_WORDS:
            self.memory.clear()
        new = [w for w in found if w not in self.memory]
        self.memory.update(zip(new, self.whole(new), strict=True))
        count = self.memory.__getitem__
        return [self.whole([t])[0] if w is None else sum(map(count, w)) for t, w in zip(texts, split, strict=True)]


@lru_cache(maxsize=4)
def load(path: str):
    """A function from a list of texts to their token counts."""
    if path.endswith(".json"):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        t = Tokenizer.from_file(path)
        t.no_truncation()
        t.no_padding()
        if version(path)[1]:
            with open(path, encoding="utf-8") as f:
                return WordCounts(t, json.load(f)["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        return lambda texts: [len(e) for e in t.encode_batch_fast(texts, add_special_tokens=False)]
    if path.endswith(".model"):
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        return lambda texts: [len(x) for x in m.encode(texts, num_threads=1)]
    raise ValueError(f"no tokenizer library for {path}")


def version(path: str) -> tuple[str, bool]:
    """(digest of the tokenizer's file, whether it folds case and white space)."""
    with open(path, "rb") as f:
        raw = f.read()
    folds = False
    if path.endswith(".json"):
        spec = json.loads(raw)
        steps = [n.get("type") for n in (spec.get("normalizer") or {}).get("normalizers", [])]
        splits = [s.get("behavior") for s in (spec.get("pre_tokenizer") or {}).get("pretokenizers", [])]
        pattern = ((spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}])[0].get("pattern", {}).get("Regex", "")
        folds = steps == ["NFC", "Replace", "Lowercase"] and splits[:1] == ["Removed"] and pattern == WORD_PATTERN
    return hashlib.sha256(raw).hexdigest()[:24], folds


def content_key(text: Column, folds: bool) -> Column:
    text = F.coalesce(text, F.lit(""))
    if folds:
        upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
        plain = F.trim(F.regexp_replace(F.translate(text, upper, lower), "[ \\t\\n\\r]+", " "))
        text = F.when(F.contains(text, F.lit("<|")), F.concat(F.lit("raw:"), text)).otherwise(F.concat(F.lit("fold:"), plain))
    return F.unhex(F.sha2(text, 256))


def encode_counts(misses: DataFrame, path: str) -> DataFrame:
    """``(key, n_tokens)`` of ``(key, text)``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = load(path)
        for b in batches:
            texts, out, held, size = b.column(1).to_pylist(), [], [], 0
            for t in texts:
                held.append(t or "")
                size += len(held[-1])
                if size >= PIECE_CHARS:
                    out += count(held)
                    held, size = [], 0
            if held:
                out += count(held)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.int64())], ["key", "n_tokens"])

    return misses.mapInArrow(tidy(run), "key binary, n_tokens long")


def count_tokens(df: DataFrame, path: str, cache: str | None = None, limit: int = 2048, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``(doc_id, n_bytes, n_tokens, over_limit)`` for every row of ``df``.

    ``path`` must be readable on every executor; ``cache`` is a shared folder that later calls
    may name again (a new private one by default).  A null text counts as empty, a null id keeps its row,
    repeated rows are repeated, other columns are ignored, an empty table gives an empty table.
    """
    spark = df.sparkSession
    ws = Workspace(spark, "token-counts")
    cache = cache or ws.path("cache")
    digest, folds = version(path)
    keyed = df.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), content_key(F.col(text), folds).alias("key"))
    schema = "key binary, n_tokens long, tokenizer string"
    one = keyed.groupBy("key").agg(F.first("text").alias("text"))

    def stored() -> DataFrame:
        rows = spark.read.schema(schema).parquet(cache).where(F.col("tokenizer") == digest)
        return rows.groupBy("key").agg(F.max("n_tokens").alias("n_tokens"))

    spark.createDataFrame([], schema).write.mode("append").partitionBy("tokenizer").parquet(cache)  # the folder exists from here on
    misses = one.join(stored(), "key", "left_anti")
    encode_counts(misses, path).withColumn("tokenizer", F.lit(digest)).write.mode("append").partitionBy("tokenizer").parquet(cache)
    out = keyed.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), "key").join(stored(), "key")
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
