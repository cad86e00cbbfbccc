"""Helpers that the training-data operators share: the shared folder, written
intermediate tables, and the byte-pair encoder used by the token operators."""

from __future__ import annotations

import json
import os
import tempfile
import uuid
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession

#: Text columns are split on exactly these bytes wherever a contract speaks of words.
WORD_SPACE = " \t\n\x0b\x0c\r"


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share, as the cluster names it.

    Only where ``spark.checkpoint.dir`` is unset (tests in one process) is a
    temporary folder taken, and remembered for the session.
    """
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get(
        "spark.varledger.shared.dir", None
    )
    if named is None:
        named = "file://" + tempfile.mkdtemp(prefix="varledger-")
        spark.conf.set("spark.varledger.shared.dir", named)
    return named.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str, *, partition_by: str | None = None) -> DataFrame:
    """Cut lineage by writing ``df`` into the shared folder and reading it back.

    Parquet with zstd is a fraction of what ``checkpoint()`` stores, and the
    copy survives the loss of any executor.
    """
    spark = df.sparkSession
    path = fresh_path(spark, name)
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(partition_by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Text behind one hash range, which is one group in one worker's memory, and
#: behind one task of such an exchange.
RANGE_BYTES, TASK_BYTES = 8 << 20, 64 << 20


def exchange_size(total: DataFrame) -> tuple[int, int]:
    """(ranges, tasks) of an exchange over texts whose bytes are the one value
    of ``total``; both are the session's shuffle partitions at least."""
    size = total.first()[0] or 0
    parts = int(total.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return max(2 * parts, -(-size // RANGE_BYTES)), max(parts, -(-size // TASK_BYTES))


def remove_path(spark: SparkSession, path: str) -> None:
    """Delete a written intermediate once nothing reads it any more."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def local_fs(path: str):
    """(pyarrow file system, path inside it) for a folder that executors share."""
    from pyarrow import fs

    if "://" not in path and not path.startswith("file:"):
        return fs.LocalFileSystem(), path
    if path.startswith("file:"):
        return fs.LocalFileSystem(), "/" + path[len("file:"):].lstrip("/")
    return fs.FileSystem.from_uri(path)


def byte_symbols() -> dict[str, int]:
    """The printable stand-ins of a byte-level vocabulary, from its public rule:
    printable Latin-1 bytes stand for themselves, the others follow from 256 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


#: Options of a merge model that change its ids.
_OPTIONS = ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "fuse_unk", "byte_fallback", "ignore_merges")


@lru_cache(maxsize=2)
def byte_bpe(path: str):
    """Encoder of a byte-level ``tokenizers`` file: text -> numpy uint32 ids.

    The vocabulary, merge order and special strings come from the file; the
    rank engine of tiktoken runs them about six times as fast as the library
    the file is written for.  That shortcut needs each merged piece's id to
    grow with its merge's place, the byte-level pattern, and none of the
    model's options, all of which is checked here; a file that breaks it is
    run by its own library.  ``tests/llm`` holds both against each other.
    """
    import public_tokenizers
    import tiktoken

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model, sym = spec["model"], byte_symbols()
    special = {t["content"]: t["id"] for t in spec["added_tokens"]}
    pre = spec.get("pre_tokenizer") or {}
    ranks = {bytes(sym[c] for c in w): i for w, i in model["vocab"].items() if w not in special}
    merged = [model["vocab"]["".join(m if isinstance(m, list) else m.split(" "))] for m in model["merges"]]
    simple = (
        spec.get("normalizer") is None
        and model.get("type", "BPE") == "BPE"
        and not any(model.get(k) for k in _OPTIONS)
        and not any(t.get("lstrip") or t.get("rstrip") or t.get("single_word") for t in spec["added_tokens"])
        and pre.get("type") == "ByteLevel"
        and pre.get("use_regex", True)
        and not pre.get("add_prefix_space")
        and merged == sorted(merged)
        and len(merged) + 256 == len(ranks)
    )
    if not simple:
        from tokenizers import Tokenizer

        slow = Tokenizer.from_file(path)
        return lambda text: np.asarray(slow.encode(text, add_special_tokens=False).ids, dtype=np.uint32)
    enc = tiktoken.Encoding(
        os.path.basename(path), pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special
    )
    core = enc._core_bpe
    allowed = set(special)

    def encode(text: str) -> np.ndarray:
        try:
            return np.frombuffer(core.encode_to_tiktoken_buffer(text, allowed), dtype=np.uint32)
        except UnicodeEncodeError:  # lone surrogates: the library's own replacement
            return np.asarray(enc.encode(text, allowed_special=allowed), dtype=np.uint32)

    return encode


@lru_cache(maxsize=2)
def vocab_size(path: str) -> int:
    """One more than the largest id of a ``tokenizers`` file."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    return 1 + max([*spec["model"]["vocab"].values(), *(t["id"] for t in spec["added_tokens"])])
