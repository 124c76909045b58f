import threading
from contextlib import contextmanager

import pytest
from pyspark.sql import functions as F

from linkedrank.functions.scoring import Margins, plain_score
from linkedrank.functions import scoring
from linkedrank.operators import evaluate, experiments, maintain, postings, stepwise, surface
from linkedrank.operators.evaluate import Prepared, StandingQuery
from linkedrank.operators.partners import PartnerCache
from linkedrank.plans import networks
from linkedrank.plans.catalog import SAMPLE, SAMPLE_MATCHES, SAMPLE_STATS, SAMPLE_WRITES, TRADE
from linkedrank.streaming import standing

# All trees of the worked example with their scores.
WORKED = {"p2": 7.0365, "a1": 4.0017, "a1-p2": 3.6794, "a3": 3.4044, "a5": 3.3626, "p5": 3.3337, "p1": 3.2814, "a5-p5": 2.2321,
          "p2-p5": 2.0740, "p1-p2": 2.0636, "a1-a3": 1.4812, "p1-p5": 1.3230}


def sample(spark):
    def rows(kind):
        out = []
        for r, (tf, dl) in SAMPLE_MATCHES.items():
            n, df, avdl = SAMPLE_STATS[kind]
            if r[0] == kind[0]:
                out.append((r, plain_score(tf, dl, n, df, avdl), plain_score(tf, dl, n, df, avdl, 0.2, 0.1)))
        return out

    matched = {k: spark.createDataFrame(rows(k), "key string, row_score double, row_ceiling double") for k in ("papers", "authors")}
    free = {"papers": spark.createDataFrame([("p3",), ("p4",)], "key string"), "authors": spark.createDataFrame([("a2",), ("a4",)], "key string"),
            "writes": spark.createDataFrame(SAMPLE_WRITES, "key string, w_author string, w_paper string")}
    best = {k: max(r[2] for r in rows(k)) for k in matched}
    q = StandingQuery(("james", "p2p"), k=3, max_size=5, slack=0)
    return Prepared(SAMPLE.bound(free), q, {}, matched, free, best, networks.generate(SAMPLE, ["papers", "authors"], 5))


def test_worked_example(spark):
    p = sample(spark)
    got = {}
    for r in evaluate.trees(p, p.networks).collect():
        got["-".join(sorted(m["key"] for m in r["members"] if m["matched"]))] = r["score"]
    assert got.keys() == WORKED.keys()
    assert all(abs(got[k] - v) < 6e-5 for k, v in WORKED.items())
    want = [7.0365, 4.0017, 3.6794]
    for answer in (evaluate.exhaustive(p, 3), evaluate.pruned(p, 3), evaluate.network_at_a_time(p, 3), evaluate.global_best_first(p, 3).top):
        assert [round(r["score"], 4) for r in answer.collect()] == want
    a = evaluate.banded(p, band0=1, growth=1)
    assert round(a.theta, 2) == 3.68 and a.bands[-1][1] < len(WORKED)
    shared, alone = evaluate.banded(p, ratio=0.0, band0=2), evaluate.banded(p, ratio=1.0, band0=2)
    assert [round(r["score"], 4) for r in shared.top.collect()] == [round(r["score"], 4) for r in alone.top.collect()] == want
    assert shared.found.count() >= alone.found.count()
    grades = {r["grade"] for r in evaluate.grade(evaluate.trees(p, p.networks), a.theta).collect()}
    assert "top" in grades and "dormant" in grades


def keys(df):
    return [(r["tree_key"], round(r["score"], 6)) for r in df.collect()]


def test_ceilings_bound_scores(spark, sf):
    p = evaluate.prepare(TRADE.load(spark, sf()), StandingQuery(("widget", "building"), k=10, max_size=4))
    t = evaluate.trees(p, p.networks)
    assert t.where("ceiling < score - 1e-12").count() == 0
    a = evaluate.banded(p)
    missing = t.join(a.found.select("tree_key"), "tree_key", "left_anti").agg(F.max("ceiling")).first()[0]
    assert missing is None or missing <= a.theta + 1e-9


@pytest.mark.parametrize("words", [("nation", "widget"), ("nosuchword",), ("4", "red")])
def test_odd_queries(spark, sf, words):
    p = evaluate.prepare(TRADE.load(spark, sf()), StandingQuery(words, k=7, max_size=3))
    assert keys(evaluate.banded(p).top) == keys(evaluate.exhaustive(p, 7))


def test_maintenance_equals_recompute(spark, sf):
    full = TRADE.load(spark, sf())
    q = StandingQuery(("widget", "building"), k=6, max_size=4, margins=Margins())
    start = full.bound(full.frames | {"customer": full.frames["customer"].where("key % 3 <> 0"), "part": full.frames["part"].where("key % 4 <> 1")})
    state = maintain.register(start, q, maintain.MaintainConfig(slack=1))
    tag = lambda d, op, at: d.withColumn("seq", F.col("key").cast("long") + at).withColumn("op", F.lit(op))
    batches = [
        {"customer": tag(full.frames["customer"].where("key % 3 = 0"), "I", 0)},
        {"part": tag(full.frames["part"].where("key % 4 = 1"), "I", 0).unionByName(tag(full.frames["part"].where("key % 4 = 2"), "D", 10**6))},
        {"customer": tag(full.frames["customer"].where("key % 5 = 0"), "D", 0), "lineitem": full.frames["lineitem"].where("line_order % 2 = 0").withColumn("seq", F.lit(1)).withColumn("op", F.lit("D"))},
        {"part": tag(full.frames["part"].where("key % 4 = 2").withColumn("text", F.lit("building widget")), "U", 0)},
    ]
    for batch in batches:
        if "part" in batch:
            batch = batch | {"part": maintain.split_updates(batch["part"])}
        before = state.top()
        state, report = maintain.apply(state, batch)
        fresh = evaluate.exhaustive(evaluate.prepare(state.schema, q), q.k)
        assert keys(state.top()) == keys(fresh)
        assert report.where("what = 'added'").count() == state.top().join(before.select("tree_key"), "tree_key", "left_anti").count()


def test_first_match_builds_new_networks(spark, sf):
    full = TRADE.load(spark, sf())
    q = StandingQuery(("widget", "zebra"), k=5, max_size=4)
    state = maintain.register(full, q)
    assert "orders" not in state.prep.matched
    change = full.frames["orders"].where("key < 40").withColumn("text", F.lit("zebra")).withColumn("seq", F.lit(1)).withColumn("op", F.lit("U"))
    state, _ = maintain.apply(state, {"orders": maintain.split_updates(change)})
    assert "orders" in state.prep.matched
    assert keys(state.top()) == keys(evaluate.exhaustive(evaluate.prepare(state.schema, q), 5))


def test_partner_cache_shares_joins(spark, sf):
    full = TRADE.load(spark, sf())
    link = next(x for x in TRADE.links if x.name == "line_part")
    rows = full.frames["part"].where("key < 20")
    on, off = PartnerCache(full), PartnerCache(full, enabled=False)
    counts = set()
    for c in (on, off):
        for _ in range(4):
            counts.add(c.along("part", rows, link).count())
    assert len(counts) == 1 and (on.selections, on.joins, off.joins) == (4, 1, 4)


def test_stream_of_changes(spark, sf, tmp_path):
    full = TRADE.load(spark, sf())
    q = StandingQuery(("widget", "building"), k=5, max_size=3)
    start = full.bound(full.frames | {"part": full.frames["part"].where("key % 2 = 0")})
    new = full.frames["part"].where("key % 2 = 1").withColumn("seq", F.col("key").cast("long")).withColumn("op", F.lit("I")).select("seq", "op", "key", "text")
    new.repartition(2).write.parquet(str(tmp_path / "feed"))
    states = standing.run_standing(spark, {"q": maintain.register(start, q)}, str(tmp_path / "feed"), "seq long, op string, key long, text string", "part", str(tmp_path / "at"))
    assert keys(states["q"].top()) == keys(evaluate.exhaustive(evaluate.prepare(full, q), 5))
    again = standing.run_standing(spark, {"q": maintain.register(start, q)}, str(tmp_path / "feed"), "seq long, op string, key long, text string", "part", str(tmp_path / "at"))
    assert keys(again["q"].top()) == keys(states["q"].top()) and again["q"].counters == states["q"].counters  # from the saved state
    assert standing.report_sink(spark, str(tmp_path / "at"), "q").select("batch").distinct().count() == 2
    e = spark.read.parquet(sf() + "/events.parquet")
    assert standing.change_counts(e).agg(F.sum("n")).first()[0] == e.count()


def test_stepwise_order_of_the_worked_example(spark):
    """Slots and rows are read in the known order, with the known bounds and trees."""
    t = stepwise.run(sample(spark))
    assert [(r.key, round(r.bound, 4)) for r in t.rounds] == [("p2", 7.4250), ("a1", 4.2314), ("a1", 3.8163), ("a3", 3.6985), ("a5", 3.6902), ("a3", 3.6892)]
    assert [sorted(round(s, 4) for _, s in r.found) for r in t.rounds] == [[7.0365], [3.6794, 4.0017], [], [], [], [1.4812, 3.4044]]
    assert round(t.next_bound, 4) == 3.6753 and round(t.theta, 4) == 3.6794
    assert [round(s, 4) for _, s in t.top(3)] == [7.0365, 4.0017, 3.6794]


@pytest.mark.parametrize("ratio", [0.0, 0.6, 1.0])
def test_stepwise_equals_banded(spark, sf, ratio):
    p = evaluate.prepare(TRADE.load(spark, sf()), StandingQuery(("widget", "building"), k=6, max_size=4))
    t = stepwise.run(p, ratio, limit=20_000)
    assert [round(s, 6) for _, s in t.top(6)] == [s for _, s in keys(evaluate.banded(p).top)]
    with pytest.raises(ValueError):
        stepwise.run(p, limit=10)


def test_postings_look_up_prunes_folders(spark, sf, tmp_path):
    full = TRADE.load(spark, sf())
    path = postings.build(full, str(tmp_path / "p"), 8)
    got = postings.lookup(spark, path, ["widget"], 8)
    assert "PartitionFilters: [" in got._jdf.queryExecution().toString()
    m = postings.matched_sets(spark, path, ["widget", "building"], 8)
    for rel in ("part", "customer"):
        counted = scoring.with_counts(full.frames[rel], ["widget", "building"]).where("tf_0 > 0 or tf_1 > 0")
        want = {(str(r["key"]), r["tf_0"], r["tf_1"], r["dl"]) for r in counted.collect()}
        assert {(r["key"], r["tf_0"], r["tf_1"], r["dl"]) for r in m.where(F.col("rel") == rel).collect()} == want
    assert postings.lookup(spark, path, ["nosuchword"], 8).count() == 0


def test_experiments_move_as_expected(spark, sf):
    found = {r["setting"]: r for r in experiments.by_ratio(spark, sf(), (0.0, 1.0)).collect()}
    assert found["0.0"]["kth"] == found["1.0"]["kth"] and found["0.0"]["found"] >= found["1.0"]["found"] and found["0.0"]["slots"] <= found["1.0"]["slots"]
    assert found["1.0"]["un_needed"] == 0 and found["0.0"]["un_needed"] >= 0 and 0 < found["0.0"]["read_ratio"] <= 1
    cache = experiments.by_cache(spark, sf(), (4,)).collect()
    on, off = (next(r for r in cache if r["cache"] is x) for x in (True, False))
    assert on["joins"] < off["joins"] and off["selections"] == on["selections"] and on["reduced"] == off["reduced"]


def test_window_counts_stream_like_batch(spark, sf, tmp_path):
    e = spark.read.parquet(sf() + "/events.parquet")
    e.repartition(3).write.parquet(str(tmp_path / "log"))
    for f in (standing.change_counts, lambda d: surface.session_counts(d)):
        out = str(tmp_path / f"out-{id(f)}")
        s = f(spark.readStream.schema(e.schema).parquet(str(tmp_path / "log")))
        s.writeStream.format("parquet").option("path", out).option("checkpointLocation", out + "-at").outputMode("append").trigger(availableNow=True).start().awaitTermination()
        got = {tuple(r) for r in spark.read.schema(s.schema).parquet(out).collect()}
        whole = {tuple(r) for r in f(e).collect()}
        assert got and got <= whole  # windows the watermark has not passed yet stay open


def test_change_workloads_join_and_change_three_relations(spark):
    from linkedrank.operators import experiments as x
    from linkedrank.plans import networks
    from linkedrank.plans.catalog import TRADE

    nets = networks.generate(TRADE, ["part", "customer"], x.CHANGED_QUERY.max_size)
    assert any({n[0] for n in net.nodes} >= {"part", "customer", *x.CHANGED} for net in nets)
    assert x.CHANGED_QUERY.k == 100 and x.BUCKETS == 7 and set(x.CHANGED) == {"part", "orders", "lineitem"}
    base = spark.range(1, 1001).withColumnRenamed("id", "key")
    for frame in (base, base.selectExpr("concat(key, '-1') AS key")):
        come = [x.change_batch(frame, ("insert",), b, x.BUCKETS).count() for b in range(x.BUCKETS)]
        assert all(come) and sum(come) == frame.where(x.numbered(frame, f"NOT ({x.FIRST})")).count()
        assert 0 < x.change_batch(frame, ("insert", "delete"), 0, x.BUCKETS).where("op = 'D'").count() < 1000


def test_recursive_partners_follow_links(spark, sf):
    from linkedrank.operators.toolbox import PORTABLE, _run
    from linkedrank.plans.catalog import LINE_ID

    read = lambda t: spark.read.parquet(f"{sf()}/{t}.parquet")
    got = {(r["rel"], r["depth"]): r["n"] for r in _run(PORTABLE["recursive_partners"])(spark, sf()).groupBy("rel", "depth").count().withColumnRenamed("count", "n").collect()}
    lines = spark.sql(f"SELECT {LINE_ID} AS id, l_orderkey, l_partkey FROM {{lineitem}}", lineitem=read("lineitem")).where("l_partkey BETWEEN 1 AND 20")
    assert (lines := lines.count()) > 20
    assert got == {("part", 0): 20, ("lineitem", 1): lines, ("orders", 2): lines, ("customer", 3): lines, ("nation", 4): lines}


@contextmanager
def within(spark, seconds):
    """Jobs that still run after so long are cancelled, which fails the test."""
    timer = threading.Timer(seconds, spark.sparkContext.cancelAllJobs)
    timer.start()
    try:
        yield
    finally:
        timer.cancel()


def hub(spark, sf, customers, others=0):
    """The trade tables with all customers in one nation and a word in so many of them; scores differ by length, but are 0 if all have the word."""
    full = TRADE.load(spark, sf())
    rows = spark.range(customers + others).selectExpr("id AS key", f"concat(if(id < {customers}, 'hubs ', 'none '), repeat('x', CAST(id % 7 AS INT))) AS text", "0 AS customer_nation")
    return full.bound(full.frames | {"customer": rows})


def test_all_answers_are_counted_without_being_written_out(spark, sf):
    p = evaluate.prepare(hub(spark, sf, 2000), StandingQuery(("hubs",), k=5, max_size=4))
    with within(spark, 60):
        got = {(r["size"], r["network"].count("customer+")): r["n_trees"] for r in evaluate.all_answers(p).collect()}
    assert got == {(1, 1): 2000, (3, 2): 2000 * 1999 // 2, (4, 3): 2000 * 1999 * 1998 // 6}


@pytest.mark.parametrize("words, size", [(("4", "red"), 4), (("nosuchword",), 3)])
def test_counted_answers_equal_joined_ones(spark, sf, words, size):
    full = TRADE.load(spark, sf())
    few = full.bound(full.frames | {"lineitem": full.frames["lineitem"].where("line_order < 1000"), "supplier": full.frames["supplier"].where("key < 0")})
    p = evaluate.prepare(few, StandingQuery(words, k=5, max_size=size))
    joined = evaluate.trees(p, p.networks).groupBy("network", "size").agg(F.count("*").alias("n_trees"))
    assert {tuple(r) for r in evaluate.all_answers(p).collect()} == {tuple(r) for r in joined.collect()}


def test_counted_answers_of_two_links_to_one_relation(spark):
    from linkedrank.plans.catalog import LIBRARY

    docs = spark.createDataFrame([(i, "die doch" if i % 2 else "die") for i in range(12)], "key long, text string").withColumn("doc_page", F.col("key"))
    cites = spark.createDataFrame([(i, i % 4, i * 5 % 12) for i in range(40)], "key long, citing long, cited long")
    none = {"author": "key long, text string", "wrote": "key long, wrote_by long, wrote_doc long", "labels": "key long, label_doc long"}
    full = LIBRARY.bound({"documents": docs, "cites": cites} | {r: spark.createDataFrame([], s) for r, s in none.items()})
    p = evaluate.prepare(full, StandingQuery(("die", "doch"), k=5, max_size=5))
    joined = evaluate.trees(p, p.networks).groupBy("network", "size").agg(F.count("*").alias("n_trees"))
    want = {tuple(r) for r in joined.collect()}
    assert {n[1] for n in want} == {1, 3, 5} and {tuple(r) for r in evaluate.all_answers(p).collect()} == want


@pytest.mark.parametrize("others", [0, 1000])
def test_exhaustive_ranks_a_hub_without_writing_its_trees_out(spark, sf, others):
    p = evaluate.prepare(hub(spark, sf, 2000, others), StandingQuery(("hubs",), k=5, max_size=4))
    with within(spark, 60):
        got = keys(evaluate.exhaustive(p, 5))
    assert got == keys(evaluate.top(evaluate.trees(p, [n for n in p.networks if n.size == 1]), 5)) and len(got) == 5


@pytest.mark.parametrize("words, size, k", [(("4", "red"), 3, 60), (("widget", "building"), 4, 200), (("nosuchword",), 3, 5)])
def test_exhaustive_equals_joined_and_sorted_trees(spark, sf, words, size, k):
    p = evaluate.prepare(TRADE.load(spark, sf()), StandingQuery(words, k=k, max_size=size))
    assert keys(evaluate.exhaustive(p, k)) == keys(evaluate.top(evaluate.trees(p, p.networks), k))


@pytest.mark.parametrize("phases", [("insert",), ("insert", "delete")])
def test_settings_of_a_workload_share_a_batch(spark, sf, monkeypatch, phases):
    calls, real = [], maintain.net_effect
    monkeypatch.setattr(maintain, "net_effect", lambda d: calls.append(1) or real(d))
    settings = [("a", maintain.MaintainConfig()), ("b", maintain.MaintainConfig(retreat=False))]
    q = StandingQuery(("widget", "building"), k=10, max_size=3)
    rows = experiments._change_run(spark, sf(), "w", settings, phases, q, ("part", "orders"), 2).collect()
    assert len(calls) == 4 and len(rows) == 4  # two relations and two batches, whatever the settings
    full = TRADE.load(spark, sf())
    want = [sum(experiments.change_batch(full.frames[r], phases, b, 2).count() for r in ("part", "orders")) for b in (0, 1)]
    assert [r["changes"] for r in rows] == want * 2
    assert all(r["seconds"] > 0 for r in rows)
