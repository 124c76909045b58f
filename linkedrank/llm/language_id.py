"""Operator 8: language identification by error-correcting output codes.

Every language gets a codeword; one binary classifier per bit, a logistic regression on hashed
byte trigrams of the whole text, predicts that bit. Decoding picks the codeword with the least
loss summed over the bits, each bit weighted by how well its classifier does on training rows
kept aside; a close runner-up flags the text as ambiguous.

Every language of the training fold is learned. Training reads a sample: SAMPLE rows in all, equally
many of each language, but up to LEAST_EACH of each however many languages there are, chosen by
hash of the id among rows that may be learned from. Prediction covers every text from end to end.

Edge cases: null texts and texts without a letter are ``und`` with score 0; without a learned
language everything is ``und``; one learned language is the answer for every text with a
letter; rows with a null language are never learned from; repeated rows are predicted alike;
extra columns are ignored or, in ``keep_identified``, passed through.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linkedrank.sources import read_table, staged

DIM = 4096
SAMPLE = 3200
LEAST_EACH = 20
STEPS, RATE = 80, 8.0
CLOSE = 0.2  # least lead of the best language's probability over the second's


def features(text: str) -> np.ndarray:
    """Root-scaled hashed counts of byte trigrams of a whole text, unit length."""
    b = np.frombuffer((" " + text.lower() + " ").encode("utf-8", "replace"), np.uint8).astype(np.int32)
    g = (b[:-2] * 31337 + b[1:-1] * 271 + b[2:] * 7) % DIM
    x = np.sqrt(np.bincount(g, minlength=DIM))
    return (x / max(1e-12, np.sqrt(x @ x))).astype(np.float32)


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def codewords(k: int) -> np.ndarray:
    """k codewords of -1/+1: all distinct splits for few languages, else a random code with large distances."""
    if k <= 1:
        return np.ones((k, 1))
    if k <= 5:
        n = 2 ** (k - 1) - 1
        return np.array([[1.0] * n] + [[1.0 if (c + 1) >> r & 1 else -1.0 for c in range(n)] for r in range(k - 1)])
    rng, best, score = np.random.default_rng(5), None, -1
    for _ in range(50):
        c = np.where(rng.random((k, max(15, int(np.ceil(10 * np.log2(k)))))) < 0.5, -1.0, 1.0)
        if k > 1000:  # random codes this long are far apart; all pairs would not fit
            return c
        d = (c.shape[1] - c @ c.T) / 2 + np.eye(k) * c.shape[1]
        if d.min() > score:
            best, score = c, d.min()
    return best


class LanguageModel:
    def __init__(self, x: np.ndarray, languages: list[str]):
        self.names = sorted(set(languages))
        self.codes = codewords(len(self.names))
        if not self.names:
            return
        place = {v: i for i, v in enumerate(self.names)}
        label = np.array([place[v] for v in languages])
        target = ((self.codes[label] + 1) / 2).astype(np.float32)
        n = len(label) - len(label) // 5  # the rest is kept aside; slices are views, not copies
        self.w, self.b = self._descend(x[:n], target[:n])
        right = ((self.margins(x[n:]) > 0) == (target[n:] > 0.5)).mean(axis=0) if n < len(label) else np.ones(self.codes.shape[1])
        self.weight = np.clip(2 * right - 1, 0.05, 1.0).astype(np.float32)
        self.w, self.b = self._descend(x, target)

    @staticmethod
    def _descend(x, target):
        w, b = np.zeros((x.shape[1], target.shape[1]), np.float32), np.zeros(target.shape[1], np.float32)
        vw, vb = np.zeros_like(w), np.zeros_like(b)
        for _ in range(STEPS):
            r = (1 / (1 + np.exp(-(x @ w + b))) - target).astype(np.float32) / max(1, len(x))
            vw, vb = 0.9 * vw - RATE * (x.T @ r + 1e-5 * w), 0.9 * vb - RATE * 0.1 * r.sum(axis=0)
            w, b = w + vw, b + vb
        return w, b

    def margins(self, x):
        return x @ self.w + self.b

    def decode(self, x) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Index of the nearest codeword, its probability, and whether the second is close."""
        m = self.margins(x)
        loss = (np.logaddexp(0, -m) * self.weight) @ (self.codes.T > 0) + (np.logaddexp(0, m) * self.weight) @ (self.codes.T < 0)
        p = np.exp(loss.min(axis=1, keepdims=True) - loss)
        p /= p.sum(axis=1, keepdims=True)
        order = np.sort(p, axis=1)
        second = order[:, -2] if p.shape[1] > 1 else np.zeros(len(p))
        return p.argmax(axis=1), order[:, -1], order[:, -1] - second < CLOSE


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> LanguageModel:
    rows = docs.select(docs[id_col].alias("id"), docs[lang_col].cast("string").alias("lang")).where(F.col("lang").isNotNull() & F.col("id").isNotNull()).where(~held_out(F.col("id")))
    top = rows.groupBy("lang").agg(F.count("*").alias("n"))
    many = max(1, top.count())
    each = max(LEAST_EACH, SAMPLE // many)
    # A hash below this share leaves about twice as many rows as are ranked, whatever the size of a language.
    share = (F.lit(2.0 * each + 64) / F.col("n")) * 2.0**64 - 2.0**63
    near = rows.join(F.broadcast(top), "lang").withColumn("h", F.xxhash64("id")).where(F.col("h") <= share).drop("n")
    w = Window.partitionBy("lang").orderBy("h", "id")
    ids = near.withColumn("r", F.row_number().over(w)).where(F.col("r") <= each)
    ids = staged(ids.select("id", "lang").distinct(), "language-sample")  # at most each * many rows
    picked = docs.select(docs[id_col].alias("id"), docs[lang_col].cast("string").alias("lang"), docs[text_col].alias("text")).join(F.broadcast(ids), ["id", "lang"], "left_semi")

    def run(batches):
        for b in batches:
            x = [features(t) for t in b["text"] if has_letter(t)]
            lang = [v for v, t in zip(b["lang"], b["text"]) if has_letter(t)]
            if not x:
                continue
            at = [np.flatnonzero(v) for v in x]
            yield pd.DataFrame({"id": [i for i, t in zip(b["id"], b["text"]) if has_letter(t)], "lang": lang, "at": at, "x": [v[i] for v, i in zip(x, at)]})

    got = picked.mapInPandas(run, f"id {docs.schema[id_col].dataType.simpleString()}, lang string, at array<int>, x array<float>")
    got = got.toPandas().sort_values(["id", "lang"], kind="stable", ignore_index=True).head(2 * each * many)
    order = np.random.default_rng(1).permutation(len(got))
    languages = list(got["lang"].iloc[order])
    x = np.zeros((len(got), DIM), np.float32)
    for row, k in enumerate(order):
        x[row, got["at"].iat[k]] = got["x"].iat[k]
    del got
    return LanguageModel(x, languages)


def _predict(model, texts) -> pd.DataFrame:
    lang, score, close = ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts), bool)
    with_letters = [i for i, t in enumerate(texts) if has_letter(t)] if model.names else []
    for at in range(0, len(with_letters), 256):
        part = with_letters[at : at + 256]
        best, p, c = model.decode(np.stack([features(texts[i]) for i in part]))
        score[part], close[part] = p, c
        for i, k in zip(part, best):
            lang[i] = model.names[k]
    return pd.DataFrame({"lang_pred": lang, "score": score, "ambiguous": close})


def predictor(spark, model):
    """A pandas UDF of the text: struct(lang_pred, score, ambiguous)."""
    shared = spark.sparkContext.broadcast(model)

    @F.pandas_udf("lang_pred string, score double, ambiguous boolean")
    def predict(text: pd.Series) -> pd.DataFrame:
        return _predict(shared.value, list(text))

    return predict


def identified(docs: DataFrame, model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    predict = predictor(docs.sparkSession, model)
    d = docs.select(docs[id_col].alias("doc_id"), predict(docs[text_col].cast("string")).alias("p"))
    return d.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "p.*")


def keep_identified(docs: DataFrame, model, text_col: str = "text") -> DataFrame:
    """Rows whose language is found; texts without a letter and near-even guesses go."""
    predict = predictor(docs.sparkSession, model)
    d = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), predict(docs[text_col].cast("string")).alias("p"))
    return d.where((F.col("p.lang_pred") != "und") & ~(F.col("p.ambiguous") & (F.col("p.score") < 0.5))).select("row.*")


def op8(spark, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return identified(docs, fit(docs))
