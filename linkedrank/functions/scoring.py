"""Tokens, term statistics, row scores and ceilings.

All of it is one scan per relation: term frequencies of the query's words are counted within
the row, the statistics are one aggregate with map-side combine, and scores are literals in a projection.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPLIT = r"[^\p{L}\p{N}]+"
S = 0.2


def tokens(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), SPLIT), "")


@dataclass(frozen=True)
class Stats:
    """Rows, mean text length, and rows per word of one relation."""

    n: int
    avdl: float
    df: dict[str, int]

    def idf(self, word: str, margin: float = 0.0) -> float:
        """ln(N / (df (1 - margin) + 1)), floored at 0 so that ceilings stay above scores."""
        return max(0.0, math.log(self.n / (self.df[word] * (1 - margin) + 1))) if self.n else 0.0


@dataclass(frozen=True)
class Margins:
    """Head-room of the bounds: df per word, avdl per relation."""

    df: float = 0.01
    avdl: float = 0.01
    df_step: float = 0.02
    df_cap: float = 0.15
    avdl_step: float = 0.01

    def wider_df(self) -> Margins:
        return replace(self, df=min(self.df_cap, self.df + self.df_step))

    def wider_avdl(self) -> Margins:
        return replace(self, avdl=self.avdl + self.avdl_step)


def occurrences(terms: Column, word: str) -> Column:
    return F.size(F.filter(terms, lambda x: x == F.lit(word)))


def with_counts(rel: DataFrame, words: list[str]) -> DataFrame:
    """Add dl and tf_0.. (occurrences of each query word)."""
    t = rel.withColumn("dl", F.length("text")).withColumn("terms", tokens(F.col("text")))
    for i, w in enumerate(words):
        t = t.withColumn(f"tf_{i}", occurrences(F.col("terms"), w))
    return t.drop("terms", "text")


def statistics(counted: DataFrame, words: list[str]) -> Stats:
    row = counted.agg(F.count("*").alias("n"), F.avg("dl").alias("avdl"), *[F.sum((F.col(f"tf_{i}") > 0).cast("long")).alias(f"df_{i}") for i in range(len(words))]).first()
    return Stats(row["n"], row["avdl"] or 0.0, {w: row[f"df_{i}"] or 0 for i, w in enumerate(words)})


def weighted(words: list[str], stats: Stats, idf: dict[str, float], avdl: float, s: float = S) -> Column:
    """Sum over words of the tf part over the length part times idf."""
    length = F.lit(1 - s) + F.col("dl") * F.lit(s) / F.lit(avdl if avdl else 1.0)
    total = F.lit(0.0)
    for i, w in enumerate(words):
        tf = F.col(f"tf_{i}")
        total = total + F.when(tf > 0, (1 + F.log(1 + F.log(F.greatest(tf, F.lit(1))))) / length * idf[w]).otherwise(0.0)
    return total


def row_scores(counted: DataFrame, words: list[str], stats: Stats, s: float = S) -> DataFrame:
    return counted.withColumn("row_score", weighted(words, stats, {w: stats.idf(w) for w in words}, stats.avdl, s))


def row_ceilings(counted: DataFrame, words: list[str], stats: Stats, margins: Margins, s: float = S) -> DataFrame:
    idf = {w: stats.idf(w, margins.df) for w in words}
    return counted.withColumn("row_ceiling", weighted(words, stats, idf, stats.avdl * (1 + margins.avdl), s))


def any_word(words: list[str]) -> Column:
    return F.greatest(*[F.col(f"tf_{i}") for i in range(len(words))], F.lit(0)) > 0


def plain_score(tf: int, dl: float, n: int, df: int, avdl: float, df_margin: float = 0.0, avdl_margin: float = 0.0, s: float = S) -> float:
    """One word's score of one row in plain Python, for worked examples."""
    idf = max(0.0, math.log(n / (df * (1 - df_margin) + 1)))
    return (1 + math.log(1 + math.log(tf))) / ((1 - s) + s * dl / (avdl * (1 + avdl_margin))) * idf
