"""A training corpus from ``documents``: rules, language, near-duplicates, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes each result to
the shared folder and reads it again as the next stage's documents. All stages but the last
keep the columns of ``documents``; the last returns the pieces of the packed sequences, each with its document's
position in the training order.

Edge cases: a null or empty text fails the base rule and goes; rows with a null id are kept as their text
deserves; of rows with one id and text one stays; an empty table gives an empty result; extra columns of
the documents are carried to the last stage, which drops them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkedrank.llm import language_id, minhash_dedup, mixing, packing, quality_rules
from linkedrank.sources import read_table, staged

SHINGLE_WORDS = 5  # near-duplicates share 0.8 of their five-word shingles; op6 takes two words


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_rules.keep_good(docs)


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return language_id.keep_identified(docs, language_id.fit(docs))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash_dedup.keep_one(docs, width=SHINGLE_WORDS)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(docs)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces in sequences; ``position`` is the place of the piece's document in the mixture's training order."""
    import public_tokenizers

    return packing.pack(in_order(docs), public_tokenizers.path("word_bpe_49k.json"), keep=("position",))


def in_order(docs: DataFrame) -> DataFrame:
    """Add ``position``: the written order of a range-sorted table, by number of file and row."""
    file = F.regexp_extract(F.col("_metadata.file_name"), r"part-(\d+)", 1).cast("long")
    return docs.withColumn("position", F.shiftleft(file, 40) + F.col("_metadata.row_index"))


STAGES = [("quality_rules", rules), ("language_id", language), ("minhash_dedup", near_duplicates), ("source_mixing", mixture), ("best_fit_packing", sequences)]

# Trained classifiers and the public tokenizer decide stages 2 and 5; SQL can't express them.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = staged(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
