"""A corpus pipeline over ``documents``: identify languages, drop near copies, remove repeats, pack.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; it is written as Parquet and read
again as the next stage's docs. All but the last return the columns of documents.

Edge cases: a null or empty text has no language and goes in the first stage; rows that repeat an
id, or have none, are documents of their own; equal texts are near copies; further columns of any
name pass through the first three stages; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from avcurate.llm import langid, packing, repeats, simhash
from avcurate.llm.common import stage, staging
from avcurate.llm.queries import table, tokenizer

#: Words of a shingle, and the similarity, of the near-duplicate stage.
SHINGLE_WORDS, SIMILARITY = 5, 0.8
#: Words of the shortest repeated passage that the repeats stage removes: more than 50.
PASSAGE_WORDS = repeats.PASSAGE_WORDS


def identify_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language that holds a fifth of their letters go."""
    return langid.keep_identified(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document with the smallest id stays."""
    return simhash.keep_one(docs, SHINGLE_WORDS, SIMILARITY)


def remove_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of PASSAGE_WORDS words and strings of 400 bytes that occur more than once go; the documents stay."""
    return repeats.remove_repeats(docs, words=PASSAGE_WORDS)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of 2048 tokens; a text that lost all its words is a piece with the end id alone."""
    return packing.pack_documents(docs, tokenizer("byte_bpe_50k.json"))


STAGES = [
    ("language_id", identify_languages),
    ("simhash_neardup", drop_near_copies),
    ("suffix_array_dedup", remove_repeated_passages),
    ("packing", pack_sequences),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, f in STAGES[:-1]:
        docs = stage(f(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


def run_to(spark: SparkSession, sf_dir: str, path: str) -> None:
    """Write the rows of ``run`` to ``path`` and remove what the stages have staged."""
    with staging(spark):
        run(spark, sf_dir).write.parquet(path)
