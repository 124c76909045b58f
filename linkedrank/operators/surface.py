"""SQL views, user functions and event windows around the ranked answers."""

from __future__ import annotations

import pandas as pd
import regex
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkedrank.functions import scoring
from linkedrank.operators import evaluate, oracles, postings
from linkedrank.operators.evaluate import StandingQuery, prepare
from linkedrank.plans.catalog import LIBRARY, TRADE, LinkedSchema
from linkedrank.queries import _SMOKE_SQL, ANSWER, Q_SMOKE, _potential_sql, _trade, network_potential, query
from linkedrank.sources import read_table
from linkedrank.streaming import standing

WORD_BREAK = regex.compile(r"[^\p{L}\p{N}]+")


def sql_view(spark: SparkSession, schema: LinkedSchema, q: StandingQuery, name: str) -> str:
    """Register the ranked answer of a query as a temporary view."""
    evaluate.banded(prepare(schema, q)).top.select(ANSWER).createOrReplaceTempView(name)
    return name


def term_counter():
    """Arrow-batched user tokenizer: number of words of a text."""

    @F.pandas_udf("long")
    def count_terms(text: pd.Series) -> pd.Series:
        return text.map(lambda t: sum(1 for w in WORD_BREAK.split(t.lower()) if w) if t is not None else 0)

    return count_terms


def top_words(k: int):
    """User aggregate: the k heaviest words of a group, over counts that are aggregated already."""

    @F.pandas_udf("string")
    def heaviest(word: pd.Series, n: pd.Series) -> str:
        best = pd.DataFrame({"w": word, "n": n}).sort_values(["n", "w"], ascending=[False, True])
        return ",".join(best["w"].head(k))

    return heaviest


def terms_function():
    """Table function terms(text): one row per word."""

    class Terms:
        def eval(self, text: str):
            for w in WORD_BREAK.split((text or "").lower()):
                if w:
                    yield (w,)

    return F.udtf(Terms, returnType="word string")


def session_counts(events: DataFrame, gap: str = "10 minutes", late: str = "2 days") -> DataFrame:
    """Bursts of changes of one user, closed after ``gap`` without any."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


query("view_topk", _SMOKE_SQL)(lambda s, d: s.table(sql_view(s, TRADE.load(s, d), Q_SMOKE, "ranked_answer")))


@query("tree_members", f"""SELECT tree_key, CAST(pos AS INTEGER) - 1 AS pos, split_part(part, ':', 1) AS rel, split_part(part, ':', 2) AS key
FROM (SELECT tree_key, unnest(string_split(tree_key, '>')) AS part, generate_subscripts(string_split(tree_key, '>'), 1) AS pos FROM ({_SMOKE_SQL}))""")
def tree_members(spark, sf_dir):
    return evaluate.banded(_trade(spark, sf_dir)).top.select("tree_key", F.posexplode("members").alias("pos", "m")).select("tree_key", "pos", "m.rel", "m.key")


query("family_weights", f"SELECT network, weight FROM ({_potential_sql()})")(lambda s, d: network_potential(s, d).select("network", "weight"))
query("udf_tokenizer", f"SELECT key, CAST(len({oracles.DUCK_TOKENS}) AS BIGINT) AS n FROM ({TRADE.duck('part')})")(
    lambda s, d: TRADE.load(s, d).frames["part"].select("key", term_counter()(F.col("text")).alias("n")))
_BRAND_WORDS = f"SELECT split_part(text, ' ', 2) AS grp, word, count(*) AS n FROM (SELECT text, unnest({oracles.DUCK_TOKENS}) AS word FROM ({TRADE.duck('part')})) GROUP BY ALL"


@query("udaf_topwords", f"SELECT grp, string_agg(word, ',' ORDER BY n DESC, word) AS words FROM (SELECT *, row_number() OVER (PARTITION BY grp ORDER BY n DESC, word) AS rn FROM ({_BRAND_WORDS})) WHERE rn <= 3 GROUP BY grp")
def udaf_topwords(spark, sf_dir):
    p = TRADE.load(spark, sf_dir).frames["part"]
    words = p.select(F.split_part("text", F.lit(" "), F.lit(2)).alias("grp"), F.explode(scoring.tokens(F.col("text"))).alias("word"))
    return words.groupBy("grp", "word").agg(F.count("*").alias("n")).groupBy("grp").agg(top_words(3)("word", "n").alias("words"))


@query("udtf_terms", f"SELECT word, count(*) AS n FROM (SELECT unnest({oracles.DUCK_TOKENS}) AS word FROM ({TRADE.duck('customer')})) GROUP BY word")
def udtf_terms(spark, sf_dir):
    spark.udtf.register("linked_terms", terms_function())
    return spark.sql("SELECT word, count(*) AS n FROM {c} c, LATERAL linked_terms(c.text) GROUP BY word", c=TRADE.load(spark, sf_dir).frames["customer"])


query("json_props", "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS k FROM events GROUP BY event_type")(
    lambda s, d: read_table(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k")))


@query("join_hints_equal", "SELECT hint, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey, (VALUES ('broadcast'), ('merge'), ('shuffle_hash')) v(hint) GROUP BY hint")
def join_hints_equal(spark, sf_dir):
    line, part = read_table(spark, sf_dir, "lineitem"), read_table(spark, sf_dir, "part")
    out = None
    for hint in ("broadcast", "merge", "shuffle_hash"):
        one = line.join(part.hint(hint), line["l_partkey"] == part["p_partkey"]).agg(F.count("*").alias("n")).select(F.lit(hint).alias("hint"), "n")
        out = one if out is None else out.unionByName(one)
    return out


_DAY = "strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M')"
_AT = "yyyy-MM-dd HH:mm"
query("tumbling_changes", f"SELECT {_DAY} AS start, event_type, count(*) AS n FROM events GROUP BY ALL")(
    lambda s, d: standing.change_counts(read_table(s, d, "events")).withColumn("start", F.date_format("start", _AT)))
query("sliding_changes", """SELECT strftime(date_trunc('day', ts) + CAST(floor(hour(ts) / 12) AS INTEGER) * INTERVAL 12 HOUR - i * INTERVAL 12 HOUR, '%Y-%m-%d %H:%M') AS start,
event_type, count(*) AS n FROM events, (VALUES (0), (1)) v(i) GROUP BY ALL""")(
    lambda s, d: standing.change_counts(read_table(s, d, "events"), "24 hours", "12 hours").withColumn("start", F.date_format("start", _AT)))
query("session_changes", """WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 10 MINUTE THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
g AS (SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM g GROUP BY user_id, s""")(
    lambda s, d: session_counts(read_table(s, d, "events")).withColumn("start", F.date_format("start", _AT)))

# --- stored postings -----------------------------------------------------------------------

_WORDS = ["widget", "building", "urgent"]
_TEXTS = [r for r, x in TRADE.relations.items() if x.has_text]
_POSTED = "\nUNION ALL ".join(f"SELECT '{r}' AS rel, CAST(key AS VARCHAR) AS key, length(text) AS dl, unnest({oracles.DUCK_TOKENS}) AS word FROM ({TRADE.duck(r)})" for r in _TEXTS)
_IN = ", ".join(f"'{w}'" for w in _WORDS)


@query("postings_lookup", f"SELECT rel, key, word, count(*) AS tf, CAST(max(dl) AS INTEGER) AS dl FROM ({_POSTED}) WHERE word IN ({_IN}) GROUP BY rel, key, word")
def postings_lookup(spark, sf_dir):
    path = postings.build(TRADE.load(spark, sf_dir), postings.default_path(spark, "lookup"), 8)
    return postings.lookup(spark, path, _WORDS, 8)


# --- workload words ------------------------------------------------------------------------

LEVELS = (4, 7, 13, 30)  # share of rows, in thousandths
_LEVEL_ROWS = ", ".join(f"({x})" for x in LEVELS)


@query("workload_words_by_level", f"""WITH d AS (SELECT word, count(DISTINCT key) AS df FROM (SELECT key, unnest({oracles.DUCK_TOKENS}) AS word FROM ({LIBRARY.duck('documents')})) GROUP BY word),
r AS (SELECT level, word, df, row_number() OVER (PARTITION BY level ORDER BY abs(df * 1000 - level * (SELECT count(*) FROM documents)), word) AS place
FROM d, (VALUES {_LEVEL_ROWS}) v(level) WHERE regexp_full_match(word, '[a-z]{{4,}}'))
SELECT CAST(level AS INTEGER) AS level, CAST(place AS INTEGER) AS place, word, df FROM r WHERE place <= 9""")
def workload_words_by_level(spark, sf_dir):
    return words_by_level(LIBRARY.load(spark, sf_dir).frames["documents"])


def words_by_level(docs: DataFrame, most: int = 9) -> DataFrame:
    """The words whose share of rows is nearest to each level; the rank limit prunes before the shuffle."""
    total = docs.count()
    df = docs.select(F.explode(F.array_distinct(scoring.tokens(F.col("text")))).alias("word")).groupBy("word").agg(F.count("*").alias("df"))
    df = df.where(F.col("word").rlike("^[a-z]{4,}$")).withColumn("level", F.explode(F.array(*[F.lit(x) for x in LEVELS])))
    near = Window.partitionBy("level").orderBy(F.abs(F.col("df") * 1000 - F.col("level") * F.lit(total)), "word")
    return df.withColumn("place", F.row_number().over(near)).where(F.col("place") <= most).select("level", "place", "word", "df")
