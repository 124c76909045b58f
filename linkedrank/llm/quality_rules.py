"""Operator 4 (native): weak supervision over quality rules.

Each rule looks at a few counts of a document and votes good, bad, or abstains. A document is
good or one of a few kinds of junk; a kind is named by the rules that are expected to agree on it.
Expectation-maximisation over the table of vote patterns (at most 3^rules rows, whatever the corpus
holds) estimates the share of each kind and how often each rule votes bad on it; the posterior
probability of "good" is the verdict. So a bad vote that no other rule backs, and that falls on documents good
otherwise, is taken for a habit of good documents; votes that agree make junk. Start values
weigh as PSEUDO documents each, whatever the corpus holds, so the data overrule them.

Everything on the executors is a Column expression. The repeated-window count works
within a row on arrays of 64-bit hashes: no explode and no shuffle of words. Two
different windows of one text share a hash with a probability under 1e-10 for texts
of 20,000 words; nothing else is approximate.

Edge cases: a null or empty text has no words and all counts 0, so it fails the base
rule; repeated rows get equal verdicts; an empty table gives an empty result and the
start values; input columns besides id and text are ignored (``scored``) or passed
through untouched (``keep_good``), whatever their names.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkedrank.sources import staged

SPACE = r"[\x20\x09-\x0D]+"
WINDOW = 8
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
EXTRA = ("n_lines", "n_distinct", "n_upper", "n_shouts")

# One rule per entry: (name, SQL test for a bad vote, SQL test for a good vote, kind of junk);
# neither: abstain. The texts are valid in Spark SQL and in DuckDB alike.
RULES = (
    ("symbols", "20 * n_symbols > n_words", "n_symbols = 0", "signs"),
    ("symbol_share", "10 * n_symbols > word_chars", "100 * n_symbols <= word_chars", "signs"),
    ("dup_lines", "n_lines >= 4 AND 10 * n_dup_lines > 3 * n_lines", "n_lines >= 4 AND 20 * n_dup_lines <= n_lines", "repetition"),
    ("repeats", "100 * n_repeat_words > 30 * n_words", "n_words >= 20 AND 20 * n_repeat_words <= n_words", "repetition"),
    ("variety", "n_words >= 40 AND 5 * n_distinct < n_words", "2 * n_distinct > n_words", "repetition"),
    ("vocabulary", "n_words >= 40 AND n_distinct * n_distinct < 9 * n_words", "n_distinct * n_distinct > 16 * n_words", "repetition"),
    ("capitals", "10 * n_upper > 4 * word_chars", "5 * n_upper <= word_chars", "shape"),
    ("word_length", "2 * word_chars < 5 * n_words OR word_chars > 12 * n_words", "word_chars >= 3 * n_words AND word_chars <= 10 * n_words", "shape"),
    ("length", "n_words < 20", "n_words >= 50", "shape"),
    ("shouts", "5 * n_shouts > n_words", "10 * n_shouts <= n_words", "shape"),
)
JUNK = ("signs", "repetition", "shape")
BASE_FAILED = "n_words < 20 OR 100 * n_repeat_words > 30 * n_words"
ROUNDS = 12
# Start values: shares of good documents and of each kind of junk, and how often a rule votes bad
# on good documents, on the kind it belongs to, and on the others.
START_GOOD, START_JUNK = 0.91, 0.03
BAD_ON_GOOD, BAD_ON_OWN, BAD_ON_OTHER = 0.01, 0.7, 0.05
PSEUDO = 20.0


def _start_rate(kind: int, i: int) -> float:
    return BAD_ON_GOOD if kind == 0 else BAD_ON_OWN if RULES[i][3] == JUNK[kind - 1] else BAD_ON_OTHER


def _start_share(kind: int) -> float:
    return START_JUNK if kind else START_GOOD


@dataclass(frozen=True)
class RuleModel:
    """Shares of good documents (first) and of each kind of junk, and P(rule i votes bad | kind, it votes)."""

    share: tuple[float, ...]
    bad: tuple[tuple[float, ...], ...]

    def accuracy(self) -> dict[str, tuple[float, float]]:
        """Per rule: how often its votes are right on good documents, and on its own kind of junk."""
        return {name: (1 - self.bad[0][i], self.bad[1 + JUNK.index(kind)][i]) for i, (name, _, _, kind) in enumerate(RULES)}

    def odds_sql(self, kind: int, vote) -> str:
        """SQL of the log odds of a kind of junk against good; vote(i) is the SQL of rule i's vote (1, 0, null)."""
        terms = [f"({math.log(self.share[kind] / self.share[0])!r}D)"]
        for i, (b, g) in enumerate(zip(self.bad[kind], self.bad[0])):
            terms.append(f"(CASE {vote(i)} WHEN 1 THEN {math.log((1 - b) / (1 - g))!r}D WHEN 0 THEN {math.log(b / g)!r}D ELSE 0D END)")
        return " + ".join(terms)


START = RuleModel(tuple(_start_share(k) for k in range(len(JUNK) + 1)), tuple(tuple(_start_rate(k, i) for i in range(len(RULES))) for k in range(len(JUNK) + 1)))


def _repeat_words(df: DataFrame) -> DataFrame:
    """From ``h`` (word hashes) and ``n_words``: words inside windows that occur twice or more."""
    pair = lambda a, b: F.xxhash64(a, b)
    key, span = "h", 1
    while span < WINDOW:  # hash of 2, 4, then 8 consecutive words
        left = F.slice(key, 1, F.greatest(F.size(key) - span, F.lit(0)))
        right = F.slice(key, span + 1, F.greatest(F.size(key) - span, F.lit(0)))
        nxt = f"h{span * 2}"
        df = df.withColumn(nxt, F.when(F.size(key) > span, F.zip_with(left, right, pair)).otherwise(F.slice(key, 1, 0)))
        df = df.drop(key)
        key, span = nxt, span * 2
    df = df.withColumn("again", F.size(F.array_distinct(key)) < F.size(key))
    # Only rows with a repeated window go on: sort (hash, place), mark equal neighbours.
    df = df.withColumn(
        "runs",
        F.when(F.col("again"), F.array_sort(F.arrays_zip(F.col(key).alias("w"), F.sequence(F.lit(1), F.size(key)).alias("p")))),
    ).drop(key)
    df = df.withColumn("same", F.when(F.col("again"), F.zip_with(
        F.col("runs"), F.slice("runs", 2, F.size("runs") - 1),
        lambda x, y: F.coalesce(x.getField("w") == y.getField("w"), F.lit(False)))))
    df = df.withColumn("either", F.when(F.col("again"), F.zip_with(
        F.col("same"), F.concat(F.array(F.lit(False)), F.slice("same", 1, F.size("same") - 1)), lambda a, b: a | b)))
    df = df.withColumn("at", F.when(F.col("again"), F.array_sort(F.array_compact(
        F.zip_with("runs", "either", lambda x, e: F.when(e, x.getField("p"))))))).drop("runs", "same", "either")
    covered = F.aggregate(
        F.zip_with("at", F.slice("at", 2, F.size("at") - 1),
                   lambda a, b: F.coalesce(F.least(b - a, F.lit(WINDOW)), F.lit(WINDOW))),
        F.lit(0).cast("long"), lambda s, x: s + x)
    return df.withColumn("n_repeat_words", F.when(F.col("again"), covered).otherwise(F.lit(0).cast("long"))).drop("at", "again")


def _kept_only(text: Column, chars: str) -> Column:
    return F.length(F.regexp_replace(text, f"[^{chars}]+", "")).cast("long")


def counts(docs: DataFrame, carry: dict[str, Column], text: Column) -> DataFrame:
    """``carry`` columns plus the counts the rules look at, one row per input row."""
    df = docs.select(*[c.alias(n) for n, c in carry.items()], F.coalesce(text.cast("string"), F.lit("")).alias("t"))
    df = df.withColumn("words", F.array_remove(F.split("t", SPACE), ""))
    df = df.withColumn("lines", F.filter(F.split("t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    df = df.select(
        *carry,
        F.size("words").cast("long").alias("n_words"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        _kept_only(F.col("t"), "#*$%&|<>").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.size("lines").cast("long").alias("n_lines"),
        _kept_only(F.col("t"), "A-Z").alias("n_upper"),
        _kept_only(F.col("t"), "!").alias("n_shouts"),
        F.transform("words", lambda w: F.xxhash64(w)).alias("h"),
    )
    df = df.withColumn("n_distinct", F.size(F.array_distinct("h")).cast("long"))
    return _repeat_words(df).select(*carry, *COUNTS, *EXTRA)


def votes_sql() -> str:
    """SQL of the vote pattern: one character per rule, 1 good, 0 bad, - abstains."""
    return " || ".join(f"(CASE WHEN {bad} THEN '0' WHEN {good} THEN '1' ELSE '-' END)" for _, bad, good, _ in RULES)


def _vote(i: int) -> str:
    return f"(CASE substr(votes, {i + 1}, 1) WHEN '1' THEN 1 WHEN '0' THEN 0 END)"


def fit(voted: DataFrame, rounds: int = ROUNDS) -> RuleModel:
    """EM over the vote patterns of documents that pass the base rule.

    Spark counts the documents of each pattern; the counts (3^rules at most) are gathered once, and the rounds are
    matrix products over them, as a Spark job a round has the driver plan and compile a large aggregate each time.
    """
    patterns = voted.where(~F.expr(BASE_FAILED)).groupBy("votes").agg(F.count("*").alias("n")).collect()
    if not patterns:
        return START
    patterns = sorted((r["votes"], r["n"]) for r in patterns)
    n = np.array([c for _, c in patterns], np.float64)
    bad, good = (np.array([[v == vote for v in votes] for votes, _ in patterns], np.float64) for vote in "01")
    start = np.array(START.share), np.array(START.bad)
    share, rate = start
    for _ in range(rounds):
        odds = np.exp(np.log(share / share[0]) + good @ np.log((1 - rate) / (1 - rate[0])).T + bad @ np.log(rate / rate[0]).T)
        part = n[:, None] * odds / odds.sum(axis=1, keepdims=True)  # documents of each pattern and kind
        hit, miss = part.T @ bad, part.T @ good
        share = (part.sum(axis=0) + PSEUDO * start[0]) / (n.sum() + PSEUDO)
        rate = (hit + PSEUDO * start[1]) / (hit + miss + PSEUDO)
    return RuleModel(tuple(share.tolist()), tuple(map(tuple, rate.tolist())))


def judged(voted: DataFrame, model: RuleModel, threshold: float = 0.5) -> DataFrame:
    """Add ``p_good``, ``base_failed`` and ``kept``."""
    odds = " + ".join(f"exp({model.odds_sql(k, _vote)})" for k in range(1, len(JUNK) + 1))
    return (
        voted.withColumn("p_good", F.expr(f"1D / (1D + {odds})"))
        .withColumn("base_failed", F.expr(BASE_FAILED))
        .withColumn("kept", ~F.col("base_failed") & (F.col("p_good") >= threshold))
    )


def scored(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Counts, votes, posterior and verdict of every document, by ``id_col``."""
    voted = staged(counts(docs, {"doc_id": docs[id_col]}, docs[text_col]).withColumn("votes", F.expr(votes_sql())), "rule-votes")
    return judged(voted, fit(voted))


def keep_good(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` with a good verdict, all columns as they came."""
    row = {"row": F.struct(*[docs[c] for c in docs.columns])}
    voted = staged(counts(docs, row, docs[text_col]).withColumn("votes", F.expr(votes_sql())), "rule-votes")
    return judged(voted, fit(voted)).where("kept").select("row.*")


def op4(spark, sf_dir: str) -> DataFrame:
    from linkedrank.sources import read_table

    return scored(read_table(spark, sf_dir, "documents")).select(
        "doc_id", *COUNTS, "base_failed", "kept", "votes", F.round("p_good", 6).alias("p_good"))


def oracle_features_sql(table: str = "documents") -> str:
    """DuckDB CTEs ``voted`` (counts and votes of every document)."""
    ws = r"[ \t\n\x0B\f\r]+"
    return f"""
src AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t FROM {table}),
wl AS (SELECT rid, doc_id, t, list_filter(regexp_split_to_array(t, '{ws}'), lambda x: x <> '') AS ws FROM src),
win AS (SELECT rid, i, array_to_string(ws[i:i + {WINDOW - 1}], ' ') AS w
        FROM (SELECT rid, ws, unnest(generate_series(1, len(ws) - {WINDOW - 1})) AS i FROM wl WHERE len(ws) >= {WINDOW})),
dupw AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, w) AS c FROM win) WHERE c > 1),
rep AS (SELECT rid, sum(least({WINDOW}, coalesce(nx - i, {WINDOW}))) AS n
        FROM (SELECT rid, i, lead(i) OVER (PARTITION BY rid ORDER BY i) AS nx FROM dupw) GROUP BY rid),
ln AS (SELECT rid, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^ \\t\\n\\x0B\\f\\r]')) AS l FROM src),
feat AS (
  SELECT wl.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
    CAST(length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols,
    CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, CAST(len(l) AS BIGINT) AS n_lines,
    CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words, CAST(len(list_distinct(ws)) AS BIGINT) AS n_distinct,
    CAST(length(regexp_replace(t, '[^A-Z]+', '', 'g')) AS BIGINT) AS n_upper,
    CAST(length(regexp_replace(t, '[^!]+', '', 'g')) AS BIGINT) AS n_shouts
  FROM wl JOIN ln USING (rid) LEFT JOIN rep USING (rid)),
voted AS (SELECT *, {votes_sql()} AS votes FROM feat)"""


def oracle_sql() -> str:
    """The whole operator in DuckDB SQL, EM rounds unrolled."""
    n, kinds = len(RULES), range(len(JUNK) + 1)
    ctes = [oracle_features_sql(), f"pat AS (SELECT votes, count(*) AS n FROM voted WHERE NOT ({BASE_FAILED}) GROUP BY votes)"]
    first = [f"{_start_share(k)}::DOUBLE AS w{k}" for k in kinds] + [f"{_start_rate(k, i)}::DOUBLE AS b{k}_{i}" for k in kinds for i in range(n)]
    ctes.append(f"m0 AS (SELECT {', '.join(first)})")

    def odds(k: int) -> str:
        votes = [f"(CASE substr(votes, {i + 1}, 1) WHEN '1' THEN ln((1 - b{k}_{i}) / (1 - b0_{i})) WHEN '0' THEN ln(b{k}_{i} / b0_{i}) ELSE 0 END)" for i in range(n)]
        return f"exp({' + '.join([f'ln(w{k} / w0)', *votes])})"

    good = f"1 / (1 + {' + '.join(odds(k) for k in kinds if k)})"
    for r in range(ROUNDS):
        cols = [f"(sum(n * q{k}) + {PSEUDO * _start_share(k)}) / (sum(n) + {PSEUDO}) AS w{k}" for k in kinds]
        for k in kinds:
            for i in range(n):
                hit, miss = (f"sum(CASE WHEN substr(votes, {i + 1}, 1) = '{v}' THEN n * q{k} ELSE 0 END)" for v in (0, 1))
                cols.append(f"({hit} + {PSEUDO * _start_rate(k, i)}) / ({hit} + {miss} + {PSEUDO}) AS b{k}_{i}")
        ctes.append(f"o{r} AS (SELECT votes, n, {', '.join(f'{odds(k)} AS o{k}' for k in kinds if k)} FROM pat, m{r})")
        total = " + ".join(["1", *[f"o{k}" for k in kinds if k]])
        ctes.append(f"e{r} AS (SELECT votes, n, {', '.join((f'o{k}' if k else '1') + f' / ({total}) AS q{k}' for k in kinds)} FROM o{r})")
        ctes.append(f"m{r + 1} AS (SELECT {', '.join(cols)} FROM e{r})")
    return (
        "WITH " + ",\n".join(ctes)
        + f"\nSELECT doc_id, {', '.join(COUNTS)}, base_failed, NOT base_failed AND q >= 0.5 AS kept, votes, round(q, 6) AS p_good"
        + f"\nFROM (SELECT *, ({BASE_FAILED}) AS base_failed, {good} AS q FROM voted, m{ROUNDS})"
    )
