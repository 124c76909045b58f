"""Stored postings (rel, key, word, tf, dl), for many queries over one snapshot.

They are partitioned by relation and word bucket, so that a look-up of a few words opens as many
folders per relation, not the texts.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkedrank.functions import scoring
from linkedrank.plans.catalog import LinkedSchema
from linkedrank.sources import shared_folder


def bucket(word: Column, buckets: int) -> Column:
    return F.pmod(F.crc32(word.cast("binary")), F.lit(buckets)).cast("int")


def postings(schema: LinkedSchema) -> DataFrame:
    """Word occurrences of every text relation; combined in the map tasks, since a row's words lie in one task."""
    out = []
    for name, spec in schema.relations.items():
        if not spec.has_text:
            continue
        words = schema.frames[name].select(
            F.lit(name).alias("rel"), F.col("key").cast("string").alias("key"), F.length("text").alias("dl"), F.explode(scoring.tokens(F.col("text"))).alias("word"))
        out.append(words.groupBy("rel", "key", "word").agg(F.count("*").alias("tf"), F.first("dl").alias("dl")))
    return reduce(DataFrame.unionByName, out)


def build(schema: LinkedSchema, path: str, buckets: int = 64, spread: int = 8) -> str:
    """Write the postings. Each bucket goes to ``spread`` tasks, so that a very common word is no hot task."""
    p = postings(schema).withColumn("bucket", bucket(F.col("word"), buckets))
    salt = F.pmod(F.xxhash64("key"), F.lit(spread))
    p.repartition("rel", "bucket", salt).write.mode("overwrite").partitionBy("rel", "bucket").option("compression", "zstd").parquet(path)
    return path


def lookup(spark: SparkSession, path: str, words: list[str], buckets: int = 64, rels: list[str] | None = None) -> DataFrame:
    """Postings of the words; bucket values are literals, so other folders are not listed."""
    at = [r[0] for r in spark.createDataFrame([(w,) for w in words], "word string").select(bucket(F.col("word"), buckets)).distinct().collect()]
    p = spark.read.parquet(path).where(F.col("bucket").isin(at) & F.col("word").isin(list(words)))
    p = p.where(F.col("rel").isin(rels)) if rels else p
    return p.select("rel", "key", "word", "tf", "dl")


def matched_sets(spark: SparkSession, path: str, words: list[str], buckets: int = 64) -> DataFrame:
    """(rel, key, dl, tf_0..) of rows with at least one word, from stored postings."""
    tf = [F.sum(F.when(F.col("word") == w, F.col("tf")).otherwise(0)).cast("long").alias(f"tf_{i}") for i, w in enumerate(words)]
    return lookup(spark, path, words, buckets).groupBy("rel", "key").agg(F.first("dl").alias("dl"), *tf)


def default_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_folder(spark)}/postings-{tag}"
