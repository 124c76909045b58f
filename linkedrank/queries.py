"""Registered queries of the engine and their DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from linkedrank.functions import scoring
from linkedrank.operators import evaluate, oracles, shared
from linkedrank.operators.evaluate import StandingQuery, prepare
from linkedrank.plans import families, networks
from linkedrank.plans.catalog import LIBRARY, TRADE

Q_SMOKE = StandingQuery(("widget", "building"), k=10, max_size=4)
Q_THREE = StandingQuery(("widget", "building", "urgent"), k=20, max_size=4)
Q_PARTS = StandingQuery(("4", "widget"), k=50, max_size=3)
Q_LIBRARY = StandingQuery(("doch", "nb7"), k=20, max_size=5)
ANSWER = ["network", "size", "tree_key", "score"]
MATCHED = {"smoke": ["part", "customer"], "three": ["part", "customer", "orders"]}

_queries: dict = {}
_oracles: dict = {}


def query(name: str, sql: str | None = None):
    def put(f):
        _queries[name] = f
        if sql:
            _oracles[name] = sql
        return f

    return put


def _trade(spark, sf_dir, q=Q_SMOKE):
    return prepare(TRADE.load(spark, sf_dir), q)


def _counted(spark, sf_dir, rel, q, schema=TRADE):
    frame = schema.load(spark, sf_dir).frames[rel]
    return scoring.with_counts(frame, list(q.words))


def _ctes(schema, q, *rels, ceilings=True):
    return "WITH " + ",\n".join(c for c in oracles.relation_ctes(schema, q, ceilings) if any(c.split(" AS ")[0].endswith("_" + r) for r in rels))


# --- text and statistics -------------------------------------------------------------------


def _terms(spark, sf_dir, rel="part", schema=TRADE):
    t = schema.load(spark, sf_dir).frames[rel]
    return t.select("key", F.explode(scoring.tokens(F.col("text"))).alias("word"))


_TERMS = "SELECT key, unnest({t}) AS word FROM ({r})"


def _terms_sql(rel, schema=TRADE):
    return _TERMS.format(t=oracles.DUCK_TOKENS, r=schema.duck(rel))


query("tokenize_terms", f"SELECT word, count(*) AS n FROM ({_terms_sql('documents', LIBRARY)}) GROUP BY word")(
    lambda s, d: _terms(s, d, "documents", LIBRARY).groupBy("word").agg(F.count("*").alias("n")))
query("term_frequency", f"SELECT key, word, count(*) AS tf FROM ({_terms_sql('part')}) GROUP BY key, word")(
    lambda s, d: _terms(s, d).groupBy("key", "word").agg(F.count("*").alias("tf")))
query("document_frequency", f"SELECT word, count(DISTINCT key) AS df FROM ({_terms_sql('part')}) GROUP BY word")(
    lambda s, d: _terms(s, d).distinct().groupBy("word").agg(F.count("*").alias("df")))


@query("relation_stats", "\nUNION ALL ".join(
    f"SELECT '{r}' AS rel, count(*) AS n, CAST(sum(length(text)) AS BIGINT) AS sum_dl FROM ({TRADE.duck(r)})" for r, x in TRADE.relations.items() if x.has_text))
def relation_stats(spark, sf_dir):
    frames = TRADE.load(spark, sf_dir).frames
    out = None
    for r, spec in TRADE.relations.items():
        if spec.has_text:
            one = frames[r].agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("sum_dl")).select(F.lit(r).alias("rel"), "n", "sum_dl")
            out = one if out is None else out.unionByName(one)
    return out


def _matched(rel, q, schema=TRADE):
    def run(spark, sf_dir):
        c = _counted(spark, sf_dir, rel, q, schema)
        return c.where(scoring.any_word(list(q.words))).select("key", "dl", *[F.col(f"tf_{i}").cast("long").alias(f"tf_{i}") for i in range(len(q.words))])

    some = " OR ".join(f"tf_{i} > 0" for i in range(len(q.words)))
    cols = ", ".join(f"CAST(tf_{i} AS BIGINT) AS tf_{i}" for i in range(len(q.words)))
    return run, _ctes(schema, q, rel) + f"\nSELECT key, CAST(dl AS INTEGER) AS dl, {cols} FROM c_{rel} WHERE {some}"


for _name, _rel, _q, _s in (("matched_part", "part", Q_SMOKE, TRADE), ("matched_documents", "documents", StandingQuery(("die", "and")), LIBRARY)):
    _f, _sql = _matched(_rel, _q, _s)
    query(_name, _sql)(_f)

query("free_customer", _ctes(TRADE, Q_SMOKE, "customer") + "\nSELECT key, customer_nation FROM f_customer")(
    lambda s, d: _counted(s, d, "customer", Q_SMOKE).where(~scoring.any_word(list(Q_SMOKE.words))).select("key", "customer_nation"))


def _scored(rel, q, schema, ceiling):
    def run(spark, sf_dir):
        words = list(q.words)
        c = _counted(spark, sf_dir, rel, q, schema)
        st = scoring.statistics(c, words)
        c = scoring.row_ceilings(scoring.row_scores(c.where(scoring.any_word(words)), words, st), words, st, q.margins)
        return c.select("key", F.round("row_ceiling" if ceiling else "row_score", 6).alias("value"))

    return run, _ctes(schema, q, rel) + f"\nSELECT key, round({'row_ceiling' if ceiling else 'row_score'}, 6) AS value FROM m_{rel}"


for _name, _rel, _q, _s, _c in (
    ("row_scores_part", "part", Q_SMOKE, TRADE, False), ("row_scores_documents", "documents", StandingQuery(("die", "and")), LIBRARY, False),
    ("row_ceilings_part", "part", Q_SMOKE, TRADE, True)):
    _f, _sql = _scored(_rel, _q, _s, _c)
    query(_name, _sql)(_f)

# --- single networks -----------------------------------------------------------------------


def _network(name, schema, q, matched, pick):
    """Count, best score and score sum of one network's trees."""
    net = next(n for n in networks.generate(schema, matched, 5) if pick(n))
    ctes = ",\n".join([*oracles.relation_ctes(schema, q, False), f"trees AS ({networks.to_sql(net)})"])
    sql = f"WITH {ctes}\nSELECT count(*) AS n_trees, round(max(score), 6) AS best, count(DISTINCT tree_key) AS n_keys FROM trees"

    def run(spark, sf_dir):
        t = evaluate.trees(prepare(schema.load(spark, sf_dir), q), [net])
        return t.agg(F.count("*").alias("n_trees"), F.round(F.max("score"), 6).alias("best"), F.count_distinct("tree_key").alias("n_keys"))

    query(name, sql)(run)


def _shape(*rels, matched=None):
    return lambda n: sorted(r for r, _ in n.nodes) == sorted(rels) and (matched is None or sum(m for _, m in n.nodes) == matched)


_network("network_single", TRADE, Q_SMOKE, ["part", "customer"], _shape("part"))
_network("network_chain3", TRADE, StandingQuery(("widget", "urgent")), ["part", "orders"], _shape("part", "lineitem", "orders"))
_network("network_chain5_matched_center", TRADE, StandingQuery(("4", "red", "urgent")), ["part", "orders"], _shape("part", "lineitem", "orders", "lineitem", "part", matched=3))
_network("network_chain5_free_center", TRADE, StandingQuery(("4", "red")), ["part"], lambda n: _shape("part", "lineitem", "orders", "lineitem", "part")(n))
_network("network_two_links", LIBRARY, StandingQuery(("doch", "die")), ["documents"], _shape("documents", "cites", "documents"))

# --- plans as tables -----------------------------------------------------------------------


@query("network_potential")
def network_potential(spark, sf_dir):
    p = _trade(spark, sf_dir)
    rows = [(n.code, n.size, round(families.potential(n, p.best), 6), round(families.weight(n, p.best), 6)) for n in p.networks]
    return spark.createDataFrame(rows, "network string, size int, potential double, weight double")


def _potential_sql():
    ctes = oracles.relation_ctes(TRADE, Q_SMOKE)
    ctes += [f"b_{r} AS (SELECT max(row_ceiling) AS b FROM m_{r})" for r in MATCHED["smoke"]]
    rows = []
    for n in networks.generate(TRADE, MATCHED["smoke"], Q_SMOKE.max_size):
        total = " + ".join(f"(SELECT b FROM b_{r})" for r, m in n.nodes if m)
        rows.append(f"SELECT '{n.code}' AS network, {n.size} AS size, round(({total}) / {n.size}, 6) AS potential, round(({total}) / {n.size} * ln({n.size} + 1), 6) AS weight")
    return "WITH " + ",\n".join(ctes) + "\n" + "\nUNION ALL ".join(rows)


_oracles["network_potential"] = _potential_sql()


@query("family_assignment")
def family_assignment(spark, sf_dir):
    p = _trade(spark, sf_dir, Q_THREE)
    rows = [(ratio, c, f) for ratio in (0.0, 0.2, 0.4, 0.6, 0.8, 1.0) for c, f in families.cluster(p.networks, p.best, ratio).items()]
    return spark.createDataFrame(rows, "ratio double, network string, family int")


# --- ranked answers ------------------------------------------------------------------------

_SMOKE_SQL, _THREE_SQL = oracles.topk(TRADE, Q_SMOKE, MATCHED["smoke"]), oracles.topk(TRADE, Q_THREE, MATCHED["three"])
_PARTS_SQL = oracles.topk(TRADE, Q_PARTS, ["orders", "part"])
_LIBRARY_SQL = oracles.topk(LIBRARY, Q_LIBRARY, ["documents", "author"])
query("exhaustive_topk_trade", _SMOKE_SQL)(lambda s, d: evaluate.exhaustive(_trade(s, d), Q_SMOKE.k).select(ANSWER))
query("initial_topk_trade", _SMOKE_SQL)(lambda s, d: evaluate.banded(_trade(s, d)).top.select(ANSWER))
query("initial_topk_pruned", _SMOKE_SQL)(lambda s, d: evaluate.pruned(_trade(s, d), Q_SMOKE.k).select(ANSWER))
query("initial_topk_three_words", _THREE_SQL)(lambda s, d: evaluate.banded(_trade(s, d, Q_THREE)).top.select(ANSWER))
query("ratio_0_topk", _THREE_SQL)(lambda s, d: evaluate.banded(_trade(s, d, Q_THREE), ratio=0.0).top.select(ANSWER))
query("ratio_1_topk", _THREE_SQL)(lambda s, d: evaluate.banded(_trade(s, d, Q_THREE), ratio=1.0).top.select(ANSWER))
query("global_best_first_topk", _SMOKE_SQL)(lambda s, d: evaluate.global_best_first(_trade(s, d), Q_SMOKE.k).top.select(ANSWER))
query("network_at_a_time_topk", _SMOKE_SQL)(lambda s, d: evaluate.network_at_a_time(_trade(s, d), Q_SMOKE.k).select(ANSWER))
query("initial_topk_tied_parts", _PARTS_SQL)(lambda s, d: evaluate.banded(_trade(s, d, Q_PARTS)).top.select(ANSWER))
query("initial_topk_library", _LIBRARY_SQL)(lambda s, d: evaluate.banded(prepare(LIBRARY.load(s, d), Q_LIBRARY)).top.select(ANSWER))

_t, _n = oracles.tree_ctes(TRADE, Q_SMOKE, MATCHED["smoke"])
query("all_answers_count", "WITH " + ",\n".join(_t) + "\nSELECT network, size, count(*) AS n_trees FROM trees GROUP BY network, size")(
    lambda s, d: evaluate.all_answers(_trade(s, d)))


@query("reduced_set_chain")
def reduced_set_chain(spark, sf_dir):
    p = _trade(spark, sf_dir)
    net = next(n for n in p.networks if n.size == 4 and any(r == "lineitem" for r, _ in n.nodes))
    out = None
    for (rel, _), f in zip(net.nodes, evaluate.reduced_chain(p, net)):
        one = f.agg(F.count("*").alias("n")).select(F.lit(rel).alias("rel"), "n")
        out = one if out is None else out.unionByName(one)
    return out


_CHAIN = "m_part p JOIN f_lineitem l ON l.line_part = p.key JOIN f_orders o ON l.line_order = o.key JOIN m_customer c ON o.orders_customer = c.key"
_oracles["reduced_set_chain"] = ("WITH " + ",\n".join(oracles.relation_ctes(TRADE, Q_SMOKE, False)) + "\n" + "\nUNION ALL ".join(
    f"SELECT '{r}' AS rel, count(DISTINCT {a}.key) AS n FROM {_CHAIN}" for r, a in (("part", "p"), ("lineitem", "l"), ("orders", "o"), ("customer", "c"))))


@query("found_grades")
def found_grades(spark, sf_dir):
    a = evaluate.banded(_trade(spark, sf_dir, Q_THREE))
    return evaluate.grade(a.found, a.theta).groupBy("grade").agg(F.count("*").alias("n"))


@query("measure_early_stop")
def measure_early_stop(spark, sf_dir):
    """Found trees, threshold, bands and read ratio per family ratio."""
    p, rows = _trade(spark, sf_dir, Q_THREE), []
    for ratio in (0.0, 0.6, 1.0):
        a = evaluate.banded(p, ratio=ratio)
        read = shared.read_ratio(p, shared.SlotPlan.of(p.networks, p.best, ratio), a.mark)
        rows.append((ratio, len(p.networks), len(a.bands), a.bands[-1][1] if a.bands else 0, a.theta, a.mark, read))
    return spark.createDataFrame(rows, "ratio double, networks int, bands int, found long, theta double, mark double, read_ratio double")


def queries() -> dict:
    from linkedrank.operators import experiments, maintain_queries, surface, toolbox  # they register themselves  # noqa: F401

    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    queries()
    return dict(_oracles)
