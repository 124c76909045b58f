"""Keeping the best k trees current under inserts and deletes.

Relations are a base and small changed parts: keys that are gone and rows that came. A batch is netted per
row and touches those parts only; texts of inserted rows alone are cut into words. Found trees carry the counts
of their members, so they are rescored by projection. Deletes take found trees away; inserts are joined outward from
the inserted rows, along partners that are fetched once per path and batch (``PartnerCache``).

``mark`` is the read mark: every tree whose ceiling reaches it is found. Ceilings come from bounds frozen per relation
and word. A live statistic above its bound widens that one margin; no ceiling grows by more than the ratio of the new
bound to the old one, so the mark rises by that ratio instead of reading anything again. Where the mark lies
above the k-th score, reading goes on from the mark (catch-up; resume, with more slack, if fewer than
k trees reach the threshold). Too many trees: the threshold and the mark rise, which un-reads rows, and the
trees below them are dropped (retreat).
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkedrank.functions import scoring
from linkedrank.functions.scoring import Margins, Stats
from linkedrank.operators import evaluate, shared
from linkedrank.operators.evaluate import Bound, Prepared, StandingQuery
from linkedrank.operators.partners import PartnerCache
from linkedrank.operators.shared import SlotPlan
from linkedrank.plans import families, networks
from linkedrank.plans.catalog import LinkedSchema
from linkedrank.sources import reread, staged, together

COUNTERS = ("batches", "changes", "df_widened", "avdl_widened", "catch_ups", "resumes", "retreats", "selections", "joins", "compactions")
HEADROOM = 0.02  # of the threshold: how far below it trees are kept found, so that small falls of scores need no reading
LAYERS, COMPACT = 8, 0.2  # batches after which the changed parts are put together; changed rows over base rows at which a relation is written anew


@dataclass(frozen=True)
class MaintainConfig:
    slack: int = 1
    slack_step: int = 2
    slack_cap: int = 20
    retreat: bool = True
    cache: bool = True
    margins: Margins = Margins()


@dataclass(frozen=True)
class Layered:
    """A relation: base rows without those whose keys are gone, and rows that came."""

    base: DataFrame
    gone: DataFrame | None = None
    come: DataFrame | None = None
    base_n: int = 0
    changed: int = 0
    layers: int = 0

    def rows(self) -> DataFrame:
        out = self.base if self.gone is None else self.base.join(F.broadcast(self.gone) if self.changed < 1_000_000 else self.gone, "key", "left_anti").select(self.base.columns)
        return out if self.come is None else out.unionByName(self.come)

    def after(self, deleted: DataFrame, inserted: DataFrame, less: int, more: int) -> Layered:
        """deleted: staged keys, less: how many rows they name; inserted: staged rows, more: how many."""
        gone, come = self.gone, self.come
        if less:
            gone = deleted if gone is None else gone.unionByName(deleted)
            come = come if come is None else come.join(deleted, "key", "left_anti").select(come.columns)
        if more:
            come = inserted if come is None else come.unionByName(inserted)
        n = less + more
        out = replace(self, gone=gone, come=come, changed=self.changed + n, layers=self.layers + (n > 0))
        if out.layers > LAYERS:
            out = out.settled()
        return out if out.changed <= COMPACT * max(self.base_n, 5000) else Layered(staged(out.rows(), "base"), base_n=self.base_n + more - less)

    def settled(self) -> Layered:
        """The same rows with the changed parts staged as one table each."""
        keep = lambda d, tag: d if d is None or hasattr(d, "staged_path") else staged(d, tag)
        return replace(self, gone=keep(self.gone, "gone"), come=keep(self.come, "come"), layers=0)


@dataclass
class State:
    schema: LinkedSchema
    query: StandingQuery
    config: MaintainConfig
    texts: dict[str, Layered]  # rows as they are given, of relations that changed
    counted: dict[str, Layered]  # key, links, dl, tf_0..; keys and links alone where there is no text
    live: dict[str, Stats]
    bounds: dict[str, Bound]
    best: dict[str, float]
    found: DataFrame
    theta: float
    mark: float
    slack: int
    counters: dict[str, int] = field(default_factory=lambda: dict.fromkeys(COUNTERS, 0))

    def top(self) -> DataFrame:
        return evaluate.top(self.found, self.query.k)

    @property
    def prep(self) -> Prepared:
        """The query over the current rows; all of it is projection over counts."""
        words, matched, free = list(self.query.words), {}, {}
        for rel, spec in self.schema.relations.items():
            rows = self.counted[rel].rows()
            if not spec.has_text:
                free[rel] = rows
                continue
            free[rel] = rows.where(~scoring.any_word(words)).select("key", *self.schema.link_columns(rel))
            if any(self.live[rel].df.values()):
                matched[rel] = evaluate.scored_rows(rows, words, self.live[rel], self.bounds[rel])
        return Prepared(self.schema, self.query, self.live, matched, free, self.best, networks.generate(self.schema, list(matched), self.query.max_size))

    def save(self, path: str) -> None:
        """Write what a restart needs as one small file; all tables are staged ones already."""
        spark = self.found.sparkSession

        def layer(x: Layered):
            at = lambda d: None if d is None else [getattr(d, "staged_path", None), d.schema.json()]
            return {"base": at(x.base), "gone": at(x.gone), "come": at(x.come), "base_n": x.base_n, "changed": x.changed}

        out = {"texts": {r: layer(x.settled()) for r, x in self.texts.items()}, "counted": {r: layer(x.settled()) for r, x in self.counted.items()}, "live": {r: asdict(x) for r, x in self.live.items()},
               "bounds": {r: asdict(x) for r, x in self.bounds.items()}, "best": self.best, "found": [self.found.staged_path, self.found.schema.json()],
               "theta": self.theta, "mark": self.mark, "slack": self.slack, "counters": self.counters}
        spark.createDataFrame([(json.dumps(out),)], "state string").coalesce(1).write.mode("overwrite").text(path)


def load(spark: SparkSession, path: str, schema: LinkedSchema, query: StandingQuery, config: MaintainConfig) -> State:
    """A saved state; schema, query and config are those it was registered with."""
    from pyspark.sql.types import StructType

    d = json.loads(spark.read.text(path, wholetext=True).first()[0])

    def table(x, given):
        return None if x is None else given if x[0] is None else reread(spark, x[0], StructType.fromJson(json.loads(x[1])))

    def layer(x, given=None):
        return Layered(table(x["base"], given), table(x["gone"], None), table(x["come"], None), x["base_n"], x["changed"])

    texts = {r: layer(x, schema.frames[r]) for r, x in d["texts"].items()}
    return State(schema.bound(schema.frames | {r: x.rows() for r, x in texts.items()}), query, config, texts,
                 {r: layer(x, schema.frames[r].select("key", *schema.link_columns(r))) for r, x in d["counted"].items()},
                 {r: Stats(**x) for r, x in d["live"].items()}, {r: Bound(**x) for r, x in d["bounds"].items()}, d["best"], table(d["found"], None),
                 d["theta"], d["mark"], d["slack"], d["counters"])


def split_updates(changes: DataFrame) -> DataFrame:
    """An update is a delete followed by an insert of the same row."""
    parts = F.when(F.col("op") == "U", F.array(F.lit("D"), F.lit("I"))).otherwise(F.array(F.col("op")))
    return changes.withColumn("op", F.explode(parts)).withColumn("seq", F.col("seq") * 2 + (F.col("op") == "I").cast("int"))


def net_effect(changes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(deleted keys, inserted rows) of changes (seq, op, key, ...): first and last op per key decide."""
    data = [c for c in changes.columns if c not in ("seq", "op")]
    n = changes.groupBy("key").agg(
        F.min_by("op", "seq").alias("first"), F.max_by(F.struct("op", *[c for c in data if c != "key"]), "seq").alias("last"))
    n = staged(n, "net")
    return n.where("first = 'D'").select("key"), n.where("last.op = 'I'").select("key", *[F.col(f"last.{c}").alias(c) for c in data if c != "key"])


def _shift(old: Stats, gone: Stats, come: Stats) -> Stats:
    n = old.n - gone.n + come.n
    total = old.avdl * old.n - gone.avdl * gone.n + come.avdl * come.n
    return Stats(n, total / n if n else 0.0, {w: old.df[w] - gone.df[w] + come.df[w] for w in old.df})


def violations(live: dict[str, Stats], bounds: dict[str, Bound]) -> list[tuple[str, str]]:
    """(relation, word) with idf above its bound, (relation, "") with mean length above it."""
    out = []
    for rel, s in live.items():
        b = bounds[rel]
        out += [(rel, w) for w, df in s.df.items() if df and s.idf(w) > b.idf[w] + 1e-12]
        if s.avdl > b.avdl + 1e-12:
            out.append((rel, ""))
    return out


def widened(bound: Bound, live: Stats, word: str, margins: Margins) -> tuple[Bound, float]:
    """The bound with one margin widened and taken from live statistics, and how much a ceiling can grow by it."""
    if not word:
        m = bound.avdl_margin + margins.avdl_step
        new = replace(bound, avdl=live.avdl * (1 + m), avdl_margin=m)
        return new, max(1.0, new.avdl / bound.avdl) if bound.avdl else float("inf")
    m = max(bound.df_margin[word], min(margins.df_cap, bound.df_margin[word] + margins.df_step))
    new = replace(bound, idf=bound.idf | {word: live.idf(word, m)}, df_margin=bound.df_margin | {word: m})
    return new, max(1.0, new.idf[word] / bound.idf[word]) if bound.idf[word] else float("inf")


def register(schema: LinkedSchema, query: StandingQuery, config: MaintainConfig = MaintainConfig()) -> State:
    words = list(query.words)

    def one(rel):
        links = schema.link_columns(rel)
        if not schema.relations[rel].has_text:
            rows = schema.frames[rel].select("key", *links)
            return Layered(rows, base_n=rows.count()), None
        rows = staged(evaluate.counted_rows(schema.frames[rel], links, words), f"counted-{rel}")
        live = scoring.statistics(rows, words)
        return Layered(rows, base_n=live.n), live

    got = dict(zip(schema.relations, together([lambda r=r: one(r) for r in schema.relations])))
    live = {r: s for r, (_, s) in got.items() if s}
    state = State(schema, query, config, {}, {r: x for r, (x, _) in got.items()}, live, {r: Bound.of(s, config.margins) for r, s in live.items()}, {}, None, 0.0, float("inf"), config.slack)
    prep = state.prep
    names = list(prep.matched)
    state.best = prep.best = dict(zip(names, together([lambda r=r: prep.matched[r].agg(F.max("row_ceiling")).first()[0] for r in names])))
    a = evaluate.banded(prep, query.k, config.slack, headroom=HEADROOM)
    state.found = a.found if hasattr(a.found, "staged_path") else staged(a.found, "found")
    state.theta, state.mark = a.theta, a.mark
    return state


def rescore(found: DataFrame, state: State) -> DataFrame:
    """Scores and ceilings of found trees from their members' counts and the current statistics and bounds."""
    words = list(state.query.words)

    def total(idf, avdl):
        def one(m):
            out = F.lit(0.0)
            for rel in state.live:
                length = F.lit(1 - scoring.S) + m["dl"] * F.lit(scoring.S) / F.lit(avdl(rel) or 1.0)
                s = F.lit(0.0)
                for i, w in enumerate(words):
                    tf = m["tf"][i]
                    s = s + F.when(tf > 0, (1 + F.log(1 + F.log(F.greatest(tf, F.lit(1))))) / length * idf(rel, w)).otherwise(0.0)
                out = F.when(m["matched"] & (m["rel"] == rel), s).otherwise(out)
            return out

        return F.aggregate("members", F.lit(0.0), lambda a, m: a + one(m)) / F.col("size")

    return found.select(
        "network", "size", "tree_key", total(lambda r, w: state.live[r].idf(w), lambda r: state.live[r].avdl).alias("score"),
        total(lambda r, w: state.bounds[r].idf[w], lambda r: state.bounds[r].avdl).alias("ceiling"), "members")


def expire(found: DataFrame, gone: dict[str, DataFrame]) -> DataFrame:
    """Found trees without those that have a deleted member."""
    dead = reduce(DataFrame.unionByName, [d.select(F.lit(rel).alias("rel"), F.col("key").cast("string").alias("key")) for rel, d in gone.items()])
    hit = found.select("tree_key", F.explode("members").alias("m")).select("tree_key", "m.rel", "m.key").join(dead, ["rel", "key"], "left_semi")
    return found.join(hit.select("tree_key").distinct(), "tree_key", "left_anti").select(found.columns)


def walk(net, i: int) -> list[tuple[int, int, tuple[str, ...]]]:
    """(node, node before it, path from i) of all nodes but i, nearest first."""
    out, todo = [], [(i, -1, ())]
    while todo:
        at, parent, path = todo.pop(0)
        if parent >= 0:
            out.append((at, parent, path))
        todo += [(j, at, (*path, label)) for j, label in net.adjacent(at) if j != parent]
    return out


def delta_trees(prep: Prepared, come: dict[str, DataFrame], peak: dict[tuple[str, bool], float], low: float, cache: bool = True) -> tuple[DataFrame, PartnerCache]:
    """Trees with an inserted row whose ceiling can reach ``low``, and the partners that were fetched for them.

    come: rows inserted per relation (key); peak: best ceiling of inserted rows by (relation, matched), absent where there are none. At node
    i the inserted rows, at nodes before it any rows, at nodes after it rows that are not new: so no tree is built twice.
    """
    flag = {rel: d.select("key").withColumn("is_new", F.lit(True)) for rel, d in come.items()}

    def rows(rel):
        r = shared.all_rows(prep, rel, {True, False})
        if rel not in flag:
            return r.withColumn("is_new", F.lit(False))
        return r.join(F.broadcast(flag[rel]), "key", "left").withColumn("is_new", F.coalesce("is_new", F.lit(False)))

    terms, least = [], {}
    for net in prep.networks:
        for i, node in enumerate(net.nodes):
            if node not in peak or (shared.rest(net, i, prep.best) + peak[node]) / net.size < low - 1e-9:
                continue
            steps = walk(net, i)
            terms.append((net, i, steps))
            for j, _, path in steps:
                rel, m = net.nodes[j]
                cut = shared.network_cut(net, j, prep.best, low) if m else None
                least.setdefault((node[0], path), {}).setdefault(m, []).append(cut)

    start = {rel: rows(rel).where("is_new") for rel in come}
    caches: dict[str, PartnerCache] = {}

    def worth(rel):
        def test(path):
            use = least.get((rel, path))
            if use is None:
                return None
            out = F.lit(False)
            if False in use:
                out = out | ~F.col("matched")
            if True in use:
                out = out | (F.col("matched") & (F.col("row_ceiling") >= min(use[True])))
            return out

        return test

    out = []
    for net, i, steps in terms:
        rel, m = net.nodes[i]
        c = caches.setdefault(rel, PartnerCache(prep.schema, cache, rows, worth(rel)))
        cut = lambda j: (F.col("row_ceiling") >= shared.network_cut(net, j, prep.best, low)) if net.nodes[j][1] else F.lit(True)  # noqa: B023, E731
        first = start[rel].where(F.col("matched") == F.lit(m)).where(cut(i))
        tree, placed = first.select(*[F.col(x).alias(f"n{i}_{x}") for x in first.columns]), {i}
        columns = {i: first.columns}
        for j, parent, path in steps:
            e = c.edges(rel, start[rel], path).where((F.col("matched") == F.lit(net.nodes[j][1])) & cut(j))
            if j > i:
                e = e.where(~F.col("is_new"))
            part = e.select(F.col("source").alias(f"n{j}_source"), *[F.col(x).alias(f"n{j}_{x}") for x in e.columns if x != "source"])
            same = [F.col(f"n{x}_key") != F.col(f"n{j}_key") for x in placed if net.nodes[x][0] == net.nodes[j][0]]
            tree = tree.join(part, reduce(lambda a, b: a & b, same, F.col(f"n{parent}_key") == F.col(f"n{j}_source")))
            placed.add(j)
            columns[j] = e.columns
        out.append(evaluate.as_trees(net, tree, [columns[j] for j in range(net.size)]))
    total = PartnerCache(prep.schema, cache)
    for rel, c in caches.items():
        total.selections, total.joins = total.selections + c.selections, total.joins + c.joins
        total.known |= {(rel, *k): d for k, d in c.known.items()}
    return (reduce(DataFrame.unionByName, out) if out else evaluate.nothing(prep)), total


def netted(changes: dict[str, DataFrame]) -> dict[str, tuple[DataFrame, DataFrame]]:
    """Net effect of each relation's changes; several queries can share it."""
    names = list(changes)
    return dict(zip(names, together([lambda r=r: net_effect(changes[r]) for r in names])))


def apply(state: State, changes: dict[str, DataFrame], net: dict | None = None) -> tuple[State, DataFrame]:
    """The state after a batch (relation -> changes), and the difference of the answers. net: ``netted(changes)`` if known."""
    query, cfg, words, before = state.query, state.config, list(state.query.words), state.top()
    net = net or netted(changes)
    texts, counted, live, counters = dict(state.texts), dict(state.counted), dict(state.live), dict(state.counters)
    counters["batches"] += 1

    def one(rel):
        deleted, inserted = net[rel]
        links, text = state.schema.link_columns(rel), state.schema.relations[rel].has_text
        raw = texts.get(rel) or Layered(state.schema.frames[rel], base_n=counted[rel].base_n)
        come = evaluate.counted_rows(inserted, links, words) if text else inserted.select("key", *links)
        old = counted[rel].rows().join(F.broadcast(deleted) if counted[rel].changed < 1_000_000 else deleted, "key", "left_semi")
        size = lambda d, sign: d.select(F.lit(sign).alias("sign"), *([F.col("dl"), *[F.col(f"tf_{i}") for i in range(len(words))]] if text else []))
        both = size(old, -1).unionByName(size(come, 1))
        df = [F.sum((F.col(f"tf_{i}") > 0).cast("long")).alias(f"df_{i}") for i in range(len(words))]
        hit = scoring.any_word(words) if text else F.lit(False)
        aggs = [F.count("*").alias("n"), F.sum(hit.cast("long")).alias("hit"), *([F.avg("dl").alias("avdl"), *df] if text else [])]
        got = {r["sign"]: r for r in both.groupBy("sign").agg(*aggs).collect()}
        stats = [Stats(r["n"], r["avdl"] or 0.0, {w: r[f"df_{i}"] or 0 for i, w in enumerate(words)}) if r and text else Stats(0, 0.0, dict.fromkeys(words, 0)) for r in (got.get(-1), got.get(1))]
        less, more = (got[sign]["n"] if sign in got else 0 for sign in (-1, 1))
        hits = got[1]["hit"] if 1 in got else 0
        return raw.after(deleted, inserted.select(raw.base.columns), less, more), counted[rel].after(deleted, come, less, more), stats, (more, hits), less + more

    done = dict(zip(net, together([lambda r=r: one(r) for r in net])))
    for rel, (raw, rows, (gone, come), _, n) in done.items():
        texts[rel], counted[rel] = raw, rows
        counters["changes"] += n
        counters["compactions"] += n > 0 and rows.changed == 0
        if state.schema.relations[rel].has_text:
            live[rel] = _shift(live[rel], gone, come)
    bounds, best, mark, grown = dict(state.bounds), dict(state.best), state.mark, 1.0
    for rel, w in violations(live, bounds):
        bounds[rel], ratio = widened(bounds[rel], live[rel], w, cfg.margins)
        counters["df_widened" if w else "avdl_widened"] += 1
        if rel in best:
            best[rel] *= ratio
        grown *= ratio
    mark *= grown
    frames = state.schema.frames | {rel: texts[rel].rows() for rel in net}
    after = replace(state, schema=state.schema.bound(frames), texts=texts, counted=counted, live=live, bounds=bounds, best=best, counters=counters)

    peak: dict[tuple[str, bool], float] = {}
    for rel, (_, _, _, (n, hits), _) in done.items():
        if n - hits:
            peak[rel, False] = 0.0
        if hits:
            c = evaluate.scored_rows(evaluate.counted_rows(net[rel][1], state.schema.link_columns(rel), words), words, live[rel], bounds[rel])
            peak[rel, True] = c.agg(F.max("row_ceiling")).first()[0]
            best[rel] = max(best.get(rel, 0.0), peak[rel, True])
    prep, k, slack = after.prep, query.k, state.slack
    for rel in [r for r, b in best.items() if b == float("inf")]:  # a bound of 0 became positive
        best[rel] = prep.matched[rel].agg(F.max("row_ceiling")).first()[0] if rel in prep.matched else 0.0
    gone = {rel: net[rel][0] for rel, (_, _, _, (more, _), n) in done.items() if n > more}
    found = rescore(expire(state.found, gone) if gone else state.found, after)
    cache = None
    if peak:
        more, cache = delta_trees(prep, {rel: i for rel, (_, i) in net.items()}, peak, mark, cfg.cache)
        found = found.unionByName(more)
        counters["selections"] += cache.selections
        counters["joins"] += cache.joins
    found = staged(found, "found")
    if cache is not None:
        cache.expire()
    theta, least = state.theta, k + slack
    scores = [r[0] for r in found.select("score").orderBy(F.desc("score")).limit(least + 1).collect()]
    kth = scores[k - 1] if len(scores) >= k else 0.0
    if mark > kth and mark > 0:
        short = len([x for x in scores if x >= theta]) < k
        if short:
            slack = min(cfg.slack_cap, slack + cfg.slack_step)
        counters["resumes" if short else "catch_ups"] += 1
        a = evaluate.read_on(prep, SlotPlan.of(prep.networks, prep.best, query.ratio), found, mark, k + slack, headroom=HEADROOM)
        found, theta, mark = a.found, a.theta, a.mark
    elif len(scores) > least and scores[least] >= theta and cfg.retreat:
        raised = scores[least - 1]
        if raised > theta:
            theta, mark = raised, max(mark, raised * (1 - HEADROOM))
            found = staged(found.where(F.col("ceiling") >= mark), "found")
            counters["retreats"] += 1
    else:
        theta = min(theta, scores[least - 1] if len(scores) >= least else kth)
    after = replace(after, found=found, theta=theta, mark=mark, slack=slack)
    return after, diff(before, after.top())


def diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """added, removed and moved trees between two answers."""
    o = old.select("tree_key", F.col("score").alias("old_score"))
    n = new.select("tree_key", F.col("score").alias("new_score"))
    what = F.when(F.col("old_score").isNull(), "added").when(F.col("new_score").isNull(), "removed").otherwise("moved")
    return o.join(n, "tree_key", "full").withColumn("what", what).where((F.col("what") != "moved") | (F.col("old_score") != F.col("new_score")))


def first_violation(changes: DataFrame, stats: Stats, words: list[str], margins: Margins, fan: int = 1024) -> DataFrame:
    """(word, seq) of the first change after which a word's live idf exceeds its bound.

    changes: (seq, n, df_0, ...) with signed steps. Running sums go over levels of ``fan`` buckets each, so that
    no task holds more than ``fan`` rows of the log; equal seqs count in one step.
    """
    cols = ["n", *[f"df_{i}" for i in range(len(words))]]
    c = changes.groupBy("seq").agg(*[F.sum(x).alias(x) for x in cols])
    span = c.agg(F.min("seq").alias("low"), F.max("seq").alias("high")).first()
    low, r = span["low"] or 0, staged(c, "log")
    widths = [fan]
    while widths[-1] < (span["high"] or 0) - low + 1:
        widths.append(widths[-1] * fan)
    sums = r.withColumn("at", F.col("seq") - F.lit(low))
    running = sums.select("seq", *[F.lit(0).cast("long").alias(f"before_{x}") for x in cols])
    for width in widths:  # sums before the own bucket of the level below, inside the bucket of this level
        part = width // fan
        level = sums.groupBy(F.floor(F.col("at") / width).alias("up"), F.floor(F.col("at") / part).alias("b")).agg(*[F.sum(x).alias(x) for x in cols])
        w = Window.partitionBy("up").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
        offset = level.select("b", *[F.coalesce(F.sum(x).over(w), F.lit(0)).alias(f"o_{x}") for x in cols])
        running = running.withColumn("b", F.floor((F.col("seq") - F.lit(low)) / part)).join(offset, "b").select(
            "seq", *[(F.col(f"before_{x}") + F.col(f"o_{x}")).alias(f"before_{x}") for x in cols])
    r = r.join(running, "seq")
    out = None
    for i, word in enumerate(words):
        n, df = F.col("n") + F.col("before_n") + stats.n, F.col(f"df_{i}") + F.col(f"before_df_{i}") + stats.df[word]
        one = r.where(F.log(n / (df + 1)) > stats.idf(word, margins.df)).agg(F.min("seq").alias("seq")).select(F.lit(word).alias("word"), "seq")
        out = one if out is None else out.unionByName(one)
    return out
