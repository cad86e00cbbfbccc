"""Corpus pipeline: language, quality, near copies, repeated passages, packing.

Every stage takes (spark, docs, sf_dir) and works on all rows it gets; all but
the last return the columns of ``documents``.  ``run`` writes each stage's
result to the shared folder and reads it again, so a lost executor costs one
stage at most.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from varledger.llm.common import written
from varledger.llm.jaccard_join import one_of_each
from varledger.llm.language_id import fit, identify
from varledger.llm.packing import pack_documents
from varledger.llm.quality import judge
from varledger.llm.substring_dedup import remove_repeats

#: A document whose language is told with less certainty goes.
LEAST_SCORE = 0.3


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, or between languages, go.

    The languages are learned from ``lang`` and ``text`` of the rows outside
    the held-out fold.  A null or empty text has no letter and goes; null ids
    and null languages are kept like others; repeated rows fare alike; without
    a labelled row every document goes.  An empty table stays empty and extra
    columns of any name pass through.
    """
    told = identify(docs, fit(docs))
    return told.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SCORE)).select("row.*")


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail the base or a rule go.

    A null or empty text has no words, so it fails the base and goes.  Only
    the text decides: null ids pass, repeated rows fare alike, an empty table
    stays empty and extra columns of any name pass through.
    """
    return judge(docs).where("kept").select("row.*")


def near_copy_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the smallest id stays.

    A null id comes after all others.  Rows are judged by themselves: of
    repeated rows one stays, and a row that only shares its id with a copy
    stays.  Texts without words link with nothing and stay.  An empty table
    stays empty and extra columns of any name pass through.
    """
    return one_of_each(docs)


def passage_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that an earlier document has, too, are cut out of the text.

    A text that loses nothing stays as it is; of others the kept words are
    joined by a space and ``n_chars``, where the table has it, follows.  A
    document of which no word is left goes; one that had none stays.  A null
    id is later than all others; rows of one id do not cut each other.  Null
    texts stay null, an empty table stays empty and extra columns of any name
    pass through.
    """
    kept = remove_repeats(docs).where("n_removed = 0 OR n_removed < n_words")
    same = F.col("n_removed") == 0
    new = {"text": F.when(same, F.col("row.text")).otherwise(F.col("kept_text"))}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(same, F.col("row.n_chars")).otherwise(F.length("kept_text"))
    types = dict(docs.dtypes)
    return kept.select(*[(new[c].cast(types[c]) if c in new else F.col(f"row.`{c}`")).alias(c) for c in docs.columns])


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 1,024 ids, as the packing query
    returns them.  A null text is its end id alone; null ids and repeated rows
    are packed like others; an empty table gives no piece; other columns are
    not read.
    """
    import public_tokenizers

    return pack_documents(docs, tokenizer=public_tokenizers.path("byte_bpe_50k.json"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language_id", language_stage),
    ("quality_rules", quality_stage),
    ("jaccard_join", near_copy_stage),
    ("substring_dedup", passage_stage),
    ("packing", packing_stage),
]

#: The first stage is a trained model, which SQL cannot express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
