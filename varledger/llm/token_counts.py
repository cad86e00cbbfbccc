"""Token counts through a digest cache.

A stored count is keyed by the SHA-256 of the normalised content and by the
tokenizer's version: the SHA-256 of its file and the normaliser's name, since
white space may be folded only where the tokenizer drops it.  Each call digests all documents, anti-joins
the distinct digests with the cache, encodes one copy of each miss, appends
those counts to the cache and joins all documents back to it.  A second call
over the same documents encodes nothing; a changed tokenizer file misses.
"""

from __future__ import annotations

import hashlib
import os
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_path, written

CACHE = "content_digest binary, tokenizer_digest string, n_tokens long"
#: Memo of one worker: space-free pieces of text and their counts.
MEMO_ENTRIES, MEMO_CHARS = 300_000, 128


def tokenizer_digest(path: str) -> str:
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()


def normalised(text: Column, *, fold: bool) -> Column:
    """Null as empty; with ``fold`` runs of ASCII white space as one space, none
    at the ends.  That keeps counts only where the tokenizer drops such runs."""
    full = F.coalesce(text, F.lit(""))
    return F.trim(F.regexp_replace(full, r"[ \t\n\x0b\f\r]+", " ")) if fold else full


@lru_cache(maxsize=2)
def _counter(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # one task, one core
    from tokenizers import Tokenizer

    tok, memo = Tokenizer.from_file(path), {}

    def count(texts: list[str]) -> list[int]:
        """White space never joins a token with its neighbours, so the count of
        a text is the sum over its pieces between spaces."""
        if len(memo) > MEMO_ENTRIES:
            memo.clear()
        split = [t.split(" ") for t in texts]
        new = list({p for pieces in split for p in pieces if p not in memo})
        own: dict[str, int] = {}
        for lo in range(0, len(new), 20_000):
            part = new[lo : lo + 20_000]
            for p, e in zip(part, tok.encode_batch_fast(part, add_special_tokens=False), strict=True):
                (memo if len(p) <= MEMO_CHARS else own)[p] = len(e)
        return [sum(memo[p] if p in memo else own[p] for p in pieces) for pieces in split]

    return count


def supports_pieces(path: str) -> bool:
    """Whether a tokenizer file drops white space between its pre-tokens."""
    import json

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    first = ((spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}])[0]
    return (
        first.get("type") == "Split"
        and first.get("behavior") == "Removed"
        and bool(first.get("invert"))
        and not any(t["lstrip"] or t["rstrip"] or " " in t["content"] for t in spec["added_tokens"])
    )


def encode_counts(docs: DataFrame, *, tokenizer: str, key_cols: list[str], text_col: str) -> DataFrame:
    """``key_cols`` and ``n_tokens`` of every row, by the tokenizer's library."""
    pieces = supports_pieces(tokenizer)
    fields = [docs.schema[c] for c in key_cols]
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in fields) + ", n_tokens long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if pieces:
            count = _counter(tokenizer)
        else:
            from tokenizers import Tokenizer

            tok = Tokenizer.from_file(tokenizer)

            def count(texts):
                return [len(tok.encode(t, add_special_tokens=False)) for t in texts]

        for whole in batches:
            for lo in range(0, whole.num_rows, 1024):
                batch = whole.slice(lo, 1024)
                texts = [t or "" for t in batch.column(len(key_cols)).to_pylist()]
                n = pa.array(count(texts), type=pa.int64())
                yield pa.RecordBatch.from_arrays([*batch.columns[:-1], n], names=[*key_cols, "n_tokens"])

    return docs.select(*key_cols, text_col).mapInArrow(run, schema)


def _exists(spark: SparkSession, path: str) -> bool:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at)


def read_cache(spark: SparkSession, path: str, version: str) -> DataFrame:
    """Digest and count of one tokenizer version; a digest that two writers
    appended at once comes out once."""
    if not _exists(spark, path):
        return spark.createDataFrame([], CACHE).drop("tokenizer_digest")
    kept = spark.read.schema(CACHE).parquet(path).where(F.col("tokenizer_digest") == version)
    return kept.groupBy("content_digest").agg(F.max("n_tokens").alias("n_tokens"))


def count_tokens(
    docs: DataFrame,
    *,
    tokenizer: str,
    cache_path: str | None = None,
    id_col: str = "doc_id",
    text_col: str = "text",
    limit: int = 2048,
) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every row.

    Null text counts as empty: no bytes, no tokens.  Null and repeated ids and
    repeated rows each give their row; an empty table gives none.  Other
    columns are not read.  ``cache_path`` names a cache that outlives the call.
    """
    spark = docs.sparkSession
    cache_path = cache_path or fresh_path(spark, "token-cache")
    fold = supports_pieces(tokenizer)
    version = f"{tokenizer_digest(tokenizer)}:{'folded' if fold else 'unchanged'}"
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    digests = written(
        rows.select(
            "doc_id",
            F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"),
            F.xxhash64("text").alias("mark"),
            F.unhex(F.sha2(normalised(F.col("text"), fold=fold), 256)).alias("content_digest"),
        ),
        "token-digests",
    )
    cached = read_cache(spark, cache_path, version)
    # One row stands for each missing digest; id and mark find its text without
    # the texts themselves being grouped.
    misses = (
        digests.groupBy("content_digest")
        .agg(F.min(F.struct("doc_id", "mark")).alias("one"))
        .join(cached, "content_digest", "left_anti")
        .select("content_digest", F.col("one.doc_id").alias("miss_id"), F.col("one.mark").alias("miss_mark"))
    )
    texts = rows.withColumn("mark", F.xxhash64("text")).join(
        misses, F.col("doc_id").eqNullSafe(F.col("miss_id")) & (F.col("mark") == F.col("miss_mark"))
    )
    counted = encode_counts(texts, tokenizer=tokenizer, key_cols=["content_digest"], text_col="text")
    counted.dropDuplicates(["content_digest"]).select(
        "content_digest", F.lit(version).alias("tokenizer_digest"), "n_tokens"
    ).write.mode("append").option("compression", "zstd").parquet(cache_path)
    # Written once more, so that both sides of the join are plain exchanges and
    # a digest that a third of the rows share is split.
    counts = written(read_cache(spark, cache_path, version), "token-counts")
    return digests.join(counts, "content_digest", "left").select(
        "doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit")
    )
