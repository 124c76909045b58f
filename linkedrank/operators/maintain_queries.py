"""Queries of the maintenance operators; the oracle of a maintained answer is brute force on the final snapshot."""

from __future__ import annotations

from pyspark.sql import functions as F

from linkedrank.functions import scoring
from linkedrank.operators import evaluate, maintain, oracles
from linkedrank.operators.partners import PartnerCache
from linkedrank.plans.catalog import TRADE
from linkedrank.queries import ANSWER, MATCHED, Q_SMOKE, query

FIRST = "(key * 7919 + 13) % 1000 < 517"  # rows of the initial snapshot
GONE = "(key * 104729 + 71) % 1000 < 328"  # rows deleted later


def _start(spark, sf_dir, rels):
    full = TRADE.load(spark, sf_dir)
    return full, full.bound({r: f.where(FIRST) if r in rels else f for r, f in full.frames.items()})


def _inserts(full, rel):
    return full.frames[rel].where(f"NOT ({FIRST})").withColumn("seq", F.col("key").cast("long")).withColumn("op", F.lit("I"))


def _deletes(full, rel, also=FIRST):
    return full.frames[rel].where(f"({GONE}) AND ({also})").withColumn("seq", F.col("key").cast("long") + 10**12).withColumn("op", F.lit("D"))


def _sql(filters):
    return oracles.topk(TRADE, Q_SMOKE, MATCHED["smoke"], filters)


@query("maintained_topk_insert", _sql({}))
def maintained_insert(spark, sf_dir):
    full, start = _start(spark, sf_dir, ["part"])
    state, _ = maintain.apply(maintain.register(start, Q_SMOKE), {"part": _inserts(full, "part")})
    return state.top().select(ANSWER)


@query("maintained_topk_delete", _sql({"customer": f"NOT ({GONE})"}))
def maintained_delete(spark, sf_dir):
    full = TRADE.load(spark, sf_dir)
    state, _ = maintain.apply(maintain.register(full, Q_SMOKE), {"customer": _deletes(full, "customer", "true")})
    return state.top().select(ANSWER)


@query("maintained_topk_mixed", _sql({"part": f"NOT (({GONE}) AND ({FIRST}))", "orders": "true"}))
def maintained_mixed(spark, sf_dir):
    full, start = _start(spark, sf_dir, ["part", "orders"])
    state, _ = maintain.apply(maintain.register(start, Q_SMOKE), {"orders": _inserts(full, "orders")})
    state, _ = maintain.apply(state, {"part": _inserts(full, "part").unionByName(_deletes(full, "part"))})
    return state.top().select(ANSWER)


@query("recompute_topk", _sql({"part": FIRST}))
def recompute(spark, sf_dir):
    """Baseline: full evaluation of a snapshot."""
    _, start = _start(spark, sf_dir, ["part"])
    return evaluate.banded(evaluate.prepare(start, Q_SMOKE)).top.select(ANSWER)


@query("maintain_counters")
def counters(spark, sf_dir):
    """Widened margins, resumes, retreats, slack and threshold; with and without retreat."""
    full, start = _start(spark, sf_dir, ["part"])
    rows = []
    for retreat in (True, False):
        s, _ = maintain.apply(maintain.register(start, Q_SMOKE, maintain.MaintainConfig(retreat=retreat)), {"part": _inserts(full, "part")})
        s, _ = maintain.apply(s, {"customer": _deletes(full, "customer", "true")})
        rows.append((retreat, s.slack, s.theta, s.found.count(), *[int(s.counters[c]) for c in ("df_widened", "avdl_widened", "catch_ups", "resumes", "retreats")]))
    return spark.createDataFrame(rows, "retreat boolean, slack int, theta double, found long, df_widened int, avdl_widened int, catch_ups int, resumes int, retreats int")


_LOG = f"SELECT key AS seq, CASE WHEN {GONE} THEN 'D' ELSE 'I' END AS op, key FROM ({{rows}})"
query("changes_log", _LOG.format(rows=TRADE.duck("part")))(
    lambda s, d: TRADE.load(s, d).frames["part"].select(F.col("key").alias("seq"), F.when(F.expr(GONE), "D").otherwise("I").alias("op"), "key"))


@query("net_changes", f"SELECT count(*) FILTER ({GONE} AND {FIRST}) AS deleted, count(*) FILTER (NOT ({FIRST})) AS inserted FROM ({TRADE.duck('part')})")
def net_changes(spark, sf_dir):
    full, _ = _start(spark, sf_dir, ["part"])
    d, i = maintain.net_effect(maintain.split_updates(_inserts(full, "part").unionByName(_deletes(full, "part"))))
    return d.agg(F.count("*").alias("deleted")).join(i.agg(F.count("*").alias("inserted")), F.lit(True))


@query("stats_after_changes", f"SELECT count(*) AS n, round(avg(length(text)), 6) AS avdl FROM ({TRADE.duck('part')}) WHERE NOT ({GONE} AND {FIRST})")
def stats_after(spark, sf_dir):
    full, start = _start(spark, sf_dir, ["part"])
    state = maintain.register(start, Q_SMOKE)
    state, _ = maintain.apply(state, {"part": _inserts(full, "part").unionByName(_deletes(full, "part"))})
    live = state.live["part"]
    return spark.createDataFrame([(live.n, round(live.avdl, 6))], "n long, avdl double")


_W = "widget"
_RUN = f"""
WITH r AS (SELECT key, text, {FIRST} AS first, len(list_filter({oracles.DUCK_TOKENS}, lambda x: x = '{_W}')) > 0 AS hit FROM ({TRADE.duck('part')})),
s AS (SELECT count(*) AS n, count(*) FILTER (hit) AS df FROM r WHERE first),
c AS (SELECT key, count(*) OVER (ORDER BY key) AS dn, count(*) FILTER (hit) OVER (ORDER BY key) AS ddf FROM r WHERE NOT first)
SELECT '{_W}' AS word, min(key) FILTER (ln((n + dn) / (df + ddf + 1)) > ln(n / (df * 0.99 + 1))) AS seq FROM c, s"""


@query("margin_watch_cumulative", _RUN)
def margin_watch(spark, sf_dir):
    full, start = _start(spark, sf_dir, ["part"])
    st = scoring.statistics(scoring.with_counts(start.frames["part"], [_W]), [_W])
    c = scoring.with_counts(_inserts(full, "part"), [_W]).select("seq", F.lit(1).alias("n"), (F.col("tf_0") > 0).cast("int").alias("df_0"))
    return maintain.first_violation(c, st, [_W], scoring.Margins())


@query("partner_cache_part", f"SELECT p.key AS source, l.key AS key FROM ({TRADE.duck('part')}) p JOIN ({TRADE.duck('lineitem')}) l ON l.line_part = p.key WHERE {GONE.replace('key', 'p.key')}")
def partner_cache(spark, sf_dir):
    full = TRADE.load(spark, sf_dir)
    link = next(x for x in TRADE.links if x.name == "line_part")
    return PartnerCache(full).along("part", full.frames["part"].where(GONE), link)


@query("partner_depth2", f"SELECT count(*) AS n FROM ({TRADE.duck('part')}) p JOIN ({TRADE.duck('lineitem')}) l ON l.line_part = p.key JOIN ({TRADE.duck('orders')}) o ON l.line_order = o.key WHERE {GONE.replace('key', 'p.key')}")
def partner_depth2(spark, sf_dir):
    full = TRADE.load(spark, sf_dir)
    cache, links = PartnerCache(full), {x.name: x for x in TRADE.links}
    lines = cache.along("part", full.frames["part"].where(GONE), links["line_part"])
    rows = full.frames["lineitem"].join(lines.select("key"), "key", "left_semi")
    return cache.within(cache.along("lineitem", rows, links["line_order"]), full.frames["orders"]).agg(F.count("*").alias("n"))


@query("snapshot_after_changes", f"SELECT count(*) AS n, CAST(sum(length(text)) AS BIGINT) AS chars, CAST(sum(key) AS BIGINT) AS keys FROM ({TRADE.duck('part')}) WHERE NOT ({GONE} AND {FIRST})")
def snapshot_after(spark, sf_dir):
    full, start = _start(spark, sf_dir, ["part"])
    state, _ = maintain.apply(maintain.register(start, Q_SMOKE), {"part": _inserts(full, "part").unionByName(_deletes(full, "part"))})
    return state.schema.frames["part"].agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("chars"), F.sum("key").cast("long").alias("keys"))


_PAIR = "(SELECT count(*) FILTER (tf_{i} > 0) FROM c_part WHERE {where})"


def _margin_sql():
    ctes = ",\n".join(c for c in oracles.relation_ctes(TRADE, Q_SMOKE, False) if c.startswith(("r_part ", "c_part ")))
    m, out = Q_SMOKE.margins, []
    old, now = f"{FIRST}", "true"
    for i, w in enumerate(Q_SMOKE.words):
        n = "(SELECT count(*) FROM c_part WHERE {where})"
        live = f"greatest(0, ln({n.format(where=now)} / ({_PAIR.format(i=i, where=now)} + 1)))"
        bound = f"greatest(0, ln({n.format(where=old)} / ({_PAIR.format(i=i, where=old)} * {1 - m.df} + 1)))"
        out.append(f"SELECT '{w}' AS word, {live} AS live, {bound} AS bound, {_PAIR.format(i=i, where=now)} > 0 AND {live} > {bound} + 1e-12 AS violated")
    live, bound = (f"(SELECT avg(dl) FROM c_part WHERE {x})" for x in (now, old))
    out.append(f"SELECT '' AS word, {live} AS live, {bound} * {1 + m.avdl} AS bound, {live} > {bound} * {1 + m.avdl} + 1e-12 AS violated")
    return f"WITH {ctes}\nSELECT word, round(live, 6) AS live, round(bound, 6) AS bound, violated FROM (" + "\nUNION ALL ".join(out) + ")"


@query("margin_violations", _margin_sql())
def margin_violations(spark, sf_dir):
    """Live idf per word and live mean length (word "") against the bounds frozen at the first snapshot."""
    full, start = _start(spark, sf_dir, ["part"])
    words, m = list(Q_SMOKE.words), Q_SMOKE.margins
    frozen, live = (scoring.statistics(scoring.with_counts(s.frames["part"], words), words) for s in (start, full))
    bound = evaluate.Bound.of(frozen, m)
    broken = set(maintain.violations({"part": live}, {"part": bound}))
    rows = [(w, round(live.idf(w), 6), round(bound.idf[w], 6), ("part", w) in broken) for w in words]
    rows.append(("", round(live.avdl, 6), round(bound.avdl, 6), ("part", "") in broken))
    return spark.createDataFrame(rows, "word string, live double, bound double, violated boolean")


@query("slack_refill", _sql({"part": f"NOT ({GONE})"}))
def slack_refill(spark, sf_dir):
    """Deletes under no slack at all: the answer runs short and reading resumes."""
    full = TRADE.load(spark, sf_dir)
    state, _ = maintain.apply(maintain.register(full, Q_SMOKE, maintain.MaintainConfig(slack=0)), {"part": _deletes(full, "part", "true")})
    return state.top().select(ANSWER)


@query("retreat_theta", f"SELECT CAST(count(*) AS INTEGER) AS n, min(score) AS kth FROM ({_sql({})})")
def retreat_theta(spark, sf_dir):
    """After inserts and a retreat, the best k found trees are still the best of all."""
    full, start = _start(spark, sf_dir, ["part"])
    state, _ = maintain.apply(maintain.register(start, Q_SMOKE), {"part": _inserts(full, "part")})
    return state.top().agg(F.count("*").cast("int").alias("n"), F.min("score").alias("kth"))
