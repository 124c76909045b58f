"""Operator 5 (native): URL filter by logistic regression on hashed character trigrams.

Domain rules decide first (longest fitting rule); every other url gets the verdict of a
logistic regression on hashed trigrams of host and path, fitted by full-batch gradient
descent on a small labelled table. A step is one aggregate over that table, whose gradient
has at most DIM entries; nothing grows with the pages.

Bounds: the labelled table is meant to hold at most LABELLED_MOST urls and the rule list at
most RULES_MOST rules; both are checked. Edge cases: null or scheme-less urls have empty host and path, no
trigrams, and the verdict of the intercept alone; urls of any length work in linear time;
repeated rows are judged alike; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkedrank.sources import read_table

DIM = 4093
STEPS, RATE, MOMENTUM, RIDGE = 60, 2.0, 0.9, 1e-3
LABELLED_MOST, RULES_MOST = 1000, 1000
THRESHOLD = 0.5
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))

# Words of the labelled urls.
BAD_WORDS = "casino poker pills pharma viagra cheap loans payday jackpot betting spam farm links replica crack keygen warez torrent adult xxx clickbait lottery bonus discount".split()
GOOD_WORDS = "library museum news docs wiki school recipes garden weather history science music travel forum archive health council books maps journal theatre nature sports parks".split()
SYLLABLES = "th er on an re he in ed nd ha at en es of or nt ea ti to it".split()


def labelled_urls() -> list[tuple[str, int]]:
    """The small labelled table: (url, 1 for block); both classes share all their templates."""
    k = len(SYLLABLES)
    plain = [SYLLABLES[i % k] + SYLLABLES[(i * 3 + 1) % k] + SYLLABLES[(i * 7 + 2) % k] for i in range(24)]
    out = []
    for words, label in ((BAD_WORDS, 1), (GOOD_WORDS, 0), (plain, 0)):
        for i, w in enumerate(words):
            v = words[(i * 7 + 3) % len(words)]
            tail = f"example.{('com', 'net', 'org')[i % 3]}/{('en', 'de', 'fr', 'es')[i % 4]}"
            out += [(f"http://{w}-{v}.{tail}/{17 * i + 5}", label), (f"https://www.{w}.{tail}/{v}/{31 * i}/", label),
                    (f"https://m.{v}-{w}.{tail}/{53 * i + 7}.html", label), (f"http://blog.{w}{v}.{tail}/{97 * i}", label)]
    return out


def host_path(url: Column) -> tuple[Column, Column]:
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), UPPER, LOWER)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def rule_for(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, else nulls."""
    if len(rules) > RULES_MOST:
        raise ValueError(f"at most {RULES_MOST} rules")
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for what, text in sorted(rules, key=lambda r: (len(r[1]), r[1])):  # later ones wrap, so the longest is asked first
        domain, slash, rest = text.partition("/")
        fits = ((host == domain) | host.endswith("." + domain)) & path.startswith(slash + rest)
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(what)).otherwise(verdict)
    return rule, verdict


def trigrams(df: DataFrame, host: str, path: str) -> DataFrame:
    """Add ``grams``: hashed trigram ids of ^host path$, other characters as one sign."""
    clean = F.regexp_replace(F.translate(F.concat(F.lit("^"), host, path, F.lit("$")), UPPER, LOWER), r"[^a-z0-9./_^$-]", "?")
    df = df.withColumn("codes", F.transform(F.array_remove(F.split(clean, ""), ""), lambda c: F.ascii(c)))
    n = F.size("codes") - 2
    at = lambda i: F.slice("codes", i, F.greatest(n, F.lit(0)))
    pairs = F.zip_with(at(1), at(2), lambda a, b: a * 7919 + b * 263)
    return df.withColumn("grams", F.zip_with(pairs, at(3), lambda p, c: (p + c) % DIM)).drop("codes")


def logit(grams: Column, weights: list[float]) -> Column:
    """weights: DIM trigram weights, then the intercept."""
    w = F.split(F.lit(",".join(map(repr, weights[:DIM]))), ",").cast("array<double>")
    total = F.aggregate(grams, F.lit(0.0), lambda s, g: s + F.get(w, g))
    return F.lit(weights[DIM]) + total / F.sqrt(F.greatest(F.size(grams), F.lit(1)))


def fit(labelled: DataFrame) -> list[float]:
    """Gradient descent on (url, label); each step is one small aggregate."""
    if labelled.count() > LABELLED_MOST:
        raise ValueError(f"at most {LABELLED_MOST} labelled urls")
    host, path = host_path(F.col("url"))
    rows = trigrams(labelled.select(host.alias("host"), path.alias("path"), F.col("label").cast("double").alias("y")), "host", "path").select("grams", "y").coalesce(1).cache()
    n, w, speed = rows.count(), [0.0] * (DIM + 1), [0.0] * (DIM + 1)
    try:
        for _ in range(STEPS if n else 0):
            r = rows.withColumn("r", F.lit(1.0) / (F.exp(-logit(F.col("grams"), w)) + 1.0) - F.col("y"))
            part = r.select(F.explode(F.concat("grams", F.array(F.lit(DIM)))).alias("g"),
                            (F.col("r") / F.sqrt(F.greatest(F.size("grams"), F.lit(1)))).alias("x"), "r")
            grad = part.groupBy("g").agg(F.sum(F.when(F.col("g") == DIM, F.col("r")).otherwise(F.col("x"))).alias("d"))
            speed = [MOMENTUM * v for v in speed]
            for g, d in grad.collect():
                speed[g] -= RATE * d / n
            w = [x * (1 - RIDGE) + v for x, v in zip(w, speed)]
    finally:
        rows.unpersist()
    return w


def fit_plain(labelled: list[tuple[str, int]]) -> list[float]:
    """The same descent in plain Python: the brute-force version for tests and for the SQL."""
    rows = []
    for url, y in labelled:
        rest = url.partition("://")[2]
        s = "^" + rest.split("?")[0].split("#")[0].lower() + "$"
        c = [ord(x) if x in "abcdefghijklmnopqrstuvwxyz0123456789./_^$-" else ord("?") for x in s]
        rows.append(([(a * 7919 + b * 263 + d) % DIM for a, b, d in zip(c, c[1:], c[2:])], y))
    w, speed = [0.0] * (DIM + 1), [0.0] * (DIM + 1)
    for _ in range(STEPS):
        grad = [0.0] * (DIM + 1)
        for g, y in rows:
            root = math.sqrt(max(1, len(g)))
            r = 1 / (1 + math.exp(-(w[DIM] + sum(w[i] for i in g) / root))) - y
            for i in g:
                grad[i] += r / root
            grad[DIM] += r
        speed = [MOMENTUM * v - RATE * d / len(rows) for v, d in zip(speed, grad)]
        w = [x * (1 - RIDGE) + v for x, v in zip(w, speed)]
    return w


def judged(urls: DataFrame, weights: list[float], url_col: str = "url", carry: tuple[str, ...] = ("page_id",), rules=RULES) -> DataFrame:
    """``carry`` columns, host, path, rule, verdict and the block probability of every row."""
    host, path = host_path(urls[url_col])
    df = urls.select(*[urls[c] for c in carry], host.alias("host"), path.alias("path"))
    rule, verdict = rule_for(F.col("host"), F.col("path"), rules)
    df = trigrams(df.withColumn("rule", rule).withColumn("said", verdict), "host", "path")
    df = df.withColumn("p_block", F.lit(1.0) / (F.exp(-logit(F.col("grams"), weights)) + 1.0))
    own = F.when(F.col("p_block") >= THRESHOLD, "block").otherwise("allow")
    return df.select(*carry, "host", "path", "rule", F.coalesce("said", own).alias("verdict"), "p_block")


def op5(spark, sf_dir: str) -> DataFrame:
    labelled = spark.createDataFrame(labelled_urls(), "url string, label int")
    return judged(read_table(spark, sf_dir, "pages"), fit(labelled)).drop("p_block")


def oracle_sql() -> str:
    w = fit_plain(labelled_urls())
    rules = "CASE " + " ".join(
        f"WHEN (host = '{t.partition('/')[0]}' OR ends_with(host, '.{t.partition('/')[0]}')) AND starts_with(path, '/{t.partition('/')[2]}') THEN '{t}'"
        for _, t in sorted(RULES, key=lambda r: -len(r[1]))) + " END"
    says = "CASE rule " + " ".join(f"WHEN '{t}' THEN '{v}'" for v, t in RULES) + " END"
    return f"""
WITH u AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), '{UPPER}', '{LOWER}') AS host,
    regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
c AS (SELECT *, {rules} AS rule, regexp_replace(translate('^' || host || path || '$', '{UPPER}', '{LOWER}'), '[^a-z0-9./_^$-]', '?', 'g') AS s FROM h),
g AS (SELECT *, list_transform(generate_series(1, length(s) - 2), lambda i:
    (unicode(substr(s, i, 1)) * 7919 + unicode(substr(s, i + 1, 1)) * 263 + unicode(substr(s, i + 2, 1))) % {DIM}) AS grams FROM c),
w AS (SELECT [{', '.join(f'{x!r}' for x in w[:DIM])}]::DOUBLE[] AS w),
z AS (SELECT g.*, {w[DIM]!r}::DOUBLE + coalesce(list_sum(list_transform(grams, lambda i: w.w[i + 1])), 0) / sqrt(greatest(len(grams), 1)) AS z FROM g, w)
SELECT page_id, host, path, rule, coalesce({says}, CASE WHEN 1 / (1 + exp(-z)) >= {THRESHOLD} THEN 'block' ELSE 'allow' END) AS verdict FROM z"""
