"""Operator 1: document quality by hierarchical empirical Bayes.

A logistic regression on hashed trigrams and a few shape counts gives each document's evidence
(log odds against the base rate). Grouped aggregation of the documents' probabilities gives,
per host and per path of a host, a count and a sum. The global rate and the spread between
hosts set the strength of the prior (method of moments of the beta distribution), hosts shrink
towards the global rate, paths towards their host. A document's quality combines its own
evidence with its path's posterior, from which its own share is taken out.

The classifier is fitted on at most SAMPLE labelled rows, chosen by hash of the id; everything
else covers all documents.

Edge cases: null or empty texts have no evidence and follow their site; null hosts or paths
are sites of their own; several labels of one id are averaged; without labels there is no
evidence and everything is kept; repeated rows count as documents; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkedrank.sources import read_table, staged

DIM, SHAPES = 4096, 4
SAMPLE = 4000
STEPS, RATE = 150, 4.0
BROADCAST_MOST = 200_000
THRESHOLD = 0.5


def features(text: str) -> np.ndarray:
    """Root-scaled hashed byte trigrams of a whole text, and shape counts."""
    raw = text.encode("utf-8", "replace")
    b = np.frombuffer(b" " + raw + b" ", np.uint8).astype(np.int32)
    x = np.sqrt(np.bincount((b[:-2] * 31337 + b[1:-1] * 271 + b[2:] * 7) % DIM, minlength=DIM))
    words = raw.split()
    n = max(1, len(words))
    shape = [len(set(words)) / n, np.mean((b >= 65) & (b <= 90)) * 4, min(1.0, np.log1p(n) / 8), len(set(raw.split(b"\n"))) / (raw.count(b"\n") + 1)]
    return np.r_[x / max(1e-12, np.sqrt(x @ x)), shape].astype(np.float32)


class Evidence:
    """Logistic regression; evidence is its log odds less those of the base rate."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.rate = float(np.clip(y.mean(), 0.01, 0.99)) if len(y) else 0.5
        self.w, b, v, vb = np.zeros(DIM + SHAPES, np.float32), 0.0, np.zeros(DIM + SHAPES, np.float32), 0.0
        self.mid = x.mean(axis=0) if len(y) else 0.0
        for _ in range(STEPS if len(y) else 0):
            z = (x - self.mid) @ self.w + b
            r = ((1 / (1 + np.exp(-z)) - y) / len(y)).astype(np.float32)
            v, vb = 0.9 * v - RATE * ((x - self.mid).T @ r + 1e-4 * self.w), 0.9 * vb - RATE * r.sum()
            self.w, b = self.w + v, b + vb
        self.b = b - np.log(self.rate / (1 - self.rate)) if len(y) else 0.0

    def __call__(self, text: str | None) -> float:
        return float(np.clip((features(text) - self.mid) @ self.w + self.b, -12, 12)) if text else 0.0


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> Evidence:
    y = labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.avg(label_col).alias("y"))
    sample = staged(y.orderBy(F.xxhash64("id"), "id").limit(SAMPLE), "quality-sample")
    rows = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text")).join(F.broadcast(sample), "id")

    def run(batches):
        for b in batches:
            b = b[b["text"].map(bool)]
            if not len(b):
                continue
            x = [features(t) for t in b["text"]]
            at = [np.flatnonzero(v) for v in x]
            yield pd.DataFrame({"id": b["id"], "y": b["y"], "at": at, "x": [v[i] for v, i in zip(x, at)]})

    got = rows.mapInPandas(run, f"id {docs.schema[id_col].dataType.simpleString()}, y double, at array<int>, x array<float>").toPandas()
    got = got.drop_duplicates("id").sort_values("id", ignore_index=True)
    x = np.zeros((len(got), DIM + SHAPES), np.float32)
    for k, (at, v) in enumerate(zip(got["at"], got["x"])):
        x[k, at] = v
    return Evidence(x, got["y"].to_numpy(np.float32))


def site_posteriors(scored: DataFrame) -> DataFrame:
    """(host, path, n, s, host_mean, prior weight of the path) from documents (host, path, p)."""
    sites = staged(scored.groupBy("host", "path").agg(F.count("*").alias("n"), F.sum("p").alias("s"), F.sum(F.col("p") * F.col("p")).alias("ss")), "sites")
    hosts = sites.groupBy("host").agg(F.sum("n").alias("hn"), F.sum("s").alias("hs"), F.sum("ss").alias("hss"))
    t = hosts.agg(
        F.sum("hn").alias("n"), F.sum("hs").alias("s"), F.count("*").alias("k"), F.sum(F.col("hs") * F.col("hs") / F.col("hn")).alias("between"),
        F.sum("hss").alias("ss"), F.sum(F.col("hn") * F.col("hn")).alias("n2")).first()
    n, k = t["n"] or 0, t["k"]
    m = min(0.999, max(0.001, t["s"] / n)) if n else 0.5
    within = max(1e-9, (t["ss"] - t["between"]) / max(1, n - k)) if n else 1.0
    size = (n - t["n2"] / n) / max(1, k - 1) if n and k > 1 else 1.0
    spread = max(1e-6, ((t["between"] - n * m * m) / max(1, k - 1) - within) / max(1e-9, size)) if n and k > 1 else 1e-6
    weight = float(min(10_000.0, max(5.0, within / spread)))
    host_mean = (F.col("hs") + weight * m) / (F.col("hn") + weight)
    # <=> joins a null host to itself
    h = hosts.select(F.col("host").alias("h"), host_mean.alias("host_mean"))
    return sites.join(h, sites["host"].eqNullSafe(h["h"])).select("host", "path", "n", "s", "host_mean", F.lit(weight).alias("weight"))


def judged(docs: DataFrame, evidence: Evidence, id_col: str = "doc_id", text_col: str = "text",
           host_col: str = "source", path_col: str = "lang", threshold: float = THRESHOLD) -> DataFrame:
    """Per document: evidence, host and path posteriors, quality and kept."""
    shared = docs.sparkSession.sparkContext.broadcast(evidence)

    @F.pandas_udf("double")
    def weigh(text: pd.Series) -> pd.Series:
        return text.map(shared.value).astype("float64")

    base = float(np.log(evidence.rate / (1 - evidence.rate)))
    d = docs.select(docs[id_col].alias("doc_id"), docs[host_col].cast("string").alias("host"), docs[path_col].cast("string").alias("path"),
                    weigh(F.coalesce(docs[text_col].cast("string"), F.lit(""))).alias("evidence"))
    d = staged(d.withColumn("p", 1 / (1 + F.exp(-(F.col("evidence") + base)))), "evidence")
    sites = staged(site_posteriors(d), "posteriors")
    s = sites.withColumnsRenamed({"host": "h", "path": "q"})
    s = F.broadcast(s) if sites.count() <= BROADCAST_MOST else s
    d = d.join(s, d["host"].eqNullSafe(s["h"]) & d["path"].eqNullSafe(s["q"])).drop("h", "q")
    path_mean = (F.col("s") - F.col("p") + F.col("weight") * F.col("host_mean")) / (F.col("n") - 1 + F.col("weight"))
    d = d.withColumn("path_mean", F.greatest(F.lit(1e-4), F.least(F.lit(1 - 1e-4), path_mean)))
    odds = F.col("evidence") + F.log(F.col("path_mean") / (1 - F.col("path_mean")))
    d = d.withColumn("quality", 1 / (1 + F.exp(-odds)))
    return d.select("doc_id", "host", "path", "evidence", "host_mean", "path_mean", "quality", (F.col("quality") >= threshold).alias("kept"))


def op1(spark, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return judged(docs, fit(docs, read_table(spark, sf_dir, "labels")))
