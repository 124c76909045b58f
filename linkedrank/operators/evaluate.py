"""Ranked evaluation of a query's networks with upper bounds.

A tree's score is the mean of its rows' scores; its ceiling the mean of the rows' ceilings. A
row of a matched set can only be in a tree of ceiling c in a network if its own ceiling plus
the best ceilings of the network's other matched nodes reaches c times the size; that is a
plain filter on the row, put below the joins. Networks are joined from the reduced sets of shared
slots (``shared``). Only statistics, maxima, histograms and the threshold reach the driver.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkedrank.functions import scoring
from linkedrank.functions.scoring import Margins, Stats
from linkedrank.operators import factored, shared
from linkedrank.operators.shared import Reduced, SlotPlan, rest
from linkedrank.plans import families, networks
from linkedrank.plans.catalog import LinkedSchema
from linkedrank.plans.networks import Network
from linkedrank.sources import staged, together

TREE = ("network string, size int, tree_key string, score double, ceiling double, "
        "members array<struct<rel:string,key:string,matched:boolean,dl:int,tf:array<int>>>")


@dataclass(frozen=True)
class StandingQuery:
    words: tuple[str, ...]
    k: int = 100
    max_size: int = 6
    ratio: float = 0.6
    slack: int = 1
    margins: Margins = Margins()
    query_id: str = "q"

    def __post_init__(self):
        if len(set(self.words)) != len(self.words):
            raise ValueError("query words must be distinct")


@dataclass(frozen=True)
class Bound:
    """Frozen upper bounds of a relation's idf per word and mean length, and the margin that each was given."""

    idf: dict[str, float]
    avdl: float
    df_margin: dict[str, float]
    avdl_margin: float

    @classmethod
    def of(cls, stats: Stats, margins: Margins) -> Bound:
        return cls({w: stats.idf(w, margins.df) for w in stats.df}, stats.avdl * (1 + margins.avdl), dict.fromkeys(stats.df, margins.df), margins.avdl)


@dataclass
class Prepared:
    """A query over one snapshot: statistics, scored matched sets, free sets, networks."""

    schema: LinkedSchema
    query: StandingQuery
    stats: dict[str, Stats]
    matched: dict[str, DataFrame]  # key, links, dl, tf_0.., row_score, row_ceiling
    free: dict[str, DataFrame]  # key, links
    best: dict[str, float]  # best row ceiling of each matched set
    networks: list[Network]


def counted_rows(frame: DataFrame, links: list[str], words: list[str]) -> DataFrame:
    """key, links, dl and tf_0.. of each row: what a query needs of a relation with text."""
    return scoring.with_counts(frame, words).select("key", *links, "dl", *[f"tf_{i}" for i in range(len(words))])


def prepare(schema: LinkedSchema, query: StandingQuery, stage: bool = True) -> Prepared:
    """One pass over each relation's text; keys, links and counts are staged, and all else reads those."""
    words = list(query.words)
    keep = staged if stage else lambda d, _: d
    texts = [r for r, spec in schema.relations.items() if spec.has_text]
    free = {r: schema.frames[r].select("key", *schema.link_columns(r)) for r in schema.relations if r not in texts}

    def one(rel):
        counted = keep(counted_rows(schema.frames[rel], schema.link_columns(rel), words), f"counted-{rel}")
        return counted, scoring.statistics(counted, words)

    got = dict(zip(texts, together([lambda r=r: one(r) for r in texts])))
    stats = {r: st for r, (_, st) in got.items()}
    for r, (counted, _) in got.items():
        free[r] = counted.where(~scoring.any_word(words)).select("key", *schema.link_columns(r))
    matched = {r: scored_rows(counted, words, st, Bound.of(st, query.margins)) for r, (counted, st) in got.items() if any(st.df.values())}
    names = list(matched)
    best = dict(zip(names, together([lambda r=r: matched[r].agg(F.max("row_ceiling")).first()[0] for r in names])))
    return Prepared(schema, query, stats, matched, free, best, networks.generate(schema, names, query.max_size))


def scored_rows(counted: DataFrame, words: list[str], live: Stats, bound: Bound) -> DataFrame:
    """The matched rows with row_score and row_ceiling, by projection."""
    m = scoring.row_scores(counted.where(scoring.any_word(words)), words, live)
    return m.withColumn("row_ceiling", scoring.weighted(words, live, bound.idf, bound.avdl))


def join_network(net: Network, frames: list[DataFrame], start: int | None = None) -> DataFrame:
    """Trees of one network; frames[i]: rows of node i (key, links, and for matched nodes row_score, row_ceiling, and dl and tf_0.. if known)."""
    parts = []
    for i, f in enumerate(frames):
        parts.append(f.select(*[F.col(c).alias(f"n{i}_{c}") for c in f.columns]))
    if start is None:
        start = min((i for i, (_, m) in enumerate(net.nodes) if m), default=0)
    out, placed = parts[start], {start}
    while len(placed) < net.size:
        c, p, link = next(e for e in net.edges if (e[0] in placed) != (e[1] in placed))
        new = p if c in placed else c
        out = out.join(parts[new], joined(net, placed, new, c, p, link))
        placed.add(new)
    return as_trees(net, out, [f.columns for f in frames])


def joined(net: Network, placed: set[int], new: int, c: int, p: int, link: str):
    """Condition that puts a row at node ``new``: the link holds, and no row is in the tree twice."""
    cond = F.col(f"n{c}_{link}") == F.col(f"n{p}_key")
    for j in placed:
        if net.nodes[j][0] == net.nodes[new][0]:
            cond = cond & (F.col(f"n{j}_key") != F.col(f"n{new}_key"))
    return cond


def as_trees(net: Network, out: DataFrame, columns: list[list[str]]) -> DataFrame:
    """Joined rows n0_.. as trees; of symmetric copies the one with the least key text stays."""
    key = [F.concat(F.lit(f"{rel}:"), F.col(f"n{i}_key").cast("string")) for i, (rel, _) in enumerate(net.nodes)]
    tree = F.concat_ws(">", *key)
    for perm in net.automorphisms:
        out = out.where(tree <= F.concat_ws(">", *[key[i] for i in perm]))
    at = [i for i, (_, m) in enumerate(net.nodes) if m]
    total = lambda c: reduce(lambda a, b: a + b, [F.col(f"n{i}_{c}") for i in at])

    def member(i, rel, m):
        tf = sorted((c for c in columns[i] if c.startswith("tf_")), key=lambda c: int(c[3:])) if m else []
        return F.struct(
            F.lit(rel).alias("rel"), F.col(f"n{i}_key").cast("string").alias("key"), F.lit(m).alias("matched"),
            (F.col(f"n{i}_dl") if tf else F.lit(None)).cast("int").alias("dl"), (F.array(*[F.col(f"n{i}_{c}") for c in tf]) if tf else F.lit(None)).cast("array<int>").alias("tf"))

    members = F.array(*[member(i, rel, m) for i, (rel, m) in enumerate(net.nodes)])
    return out.select(
        F.lit(net.code).alias("network"), F.lit(net.size).alias("size"), tree.alias("tree_key"), (total("row_score") / net.size).alias("score"),
        (total("row_ceiling") / net.size).alias("ceiling"), members.alias("members"))


def nothing(prep: Prepared) -> DataFrame:
    return next(iter(prep.schema.frames.values())).sparkSession.createDataFrame([], TREE)


def trees(prep: Prepared, nets: list[Network], cut=None) -> DataFrame:
    """Union of the networks' trees, each network joined by itself; cut(net, i): least row ceiling at a matched node, or None."""
    out = []
    for net in nets:
        frames = []
        for i, (rel, m) in enumerate(net.nodes):
            if not m:
                frames.append(prep.free[rel])
                continue
            low = cut(net, i) if cut else None
            frames.append(prep.matched[rel] if low is None else prep.matched[rel].where(F.col("row_ceiling") >= low))
        out.append(join_network(net, frames))
    return reduce(DataFrame.unionByName, out) if out else nothing(prep)


def shared_trees(prep: Prepared, plan: SlotPlan, done: Reduced, nets: list[Network], mark: float = float("inf"), now: dict | None = None) -> DataFrame:
    """Trees of the networks from the reduced sets of their slots.

    mark, now: the last frontier and the cuts at this one. Networks that took part at the last give only trees with a row read
    in between, by one join per matched node: "read before" at the nodes ahead of it, "read now" at it, either at those after it.
    """
    joined_before = {n.code for n in plan.networks if families.potential(n, prep.best) >= mark - 1e-9}
    before = plan.cuts(prep.best, mark, [n for n in plan.networks if n.code in joined_before]) if joined_before else {}
    out = []
    for net in nets:
        slot, root = plan.places[net.code], net.center()
        frames = [done.rows(slot[i]) for i in range(net.size)]
        if net.code not in joined_before:
            out.append(join_network(net, frames, root))
            continue
        at = [i for i, (_, m) in enumerate(net.nodes) if m]
        for i in at:
            if before[slot[i]] <= now[slot[i]]:
                continue
            part = list(frames)
            for j in at[: at.index(i)]:
                part[j] = frames[j].where(F.col("row_ceiling") >= before[slot[j]])
            part[i] = frames[i].where(F.col("row_ceiling") < before[slot[i]])
            out.append(join_network(net, part, root))
    return reduce(DataFrame.unionByName, out) if out else nothing(prep)


def top(found: DataFrame, k: int) -> DataFrame:
    """Best k trees; ties by size, network and tree key, so that reruns agree."""
    return found.withColumn("score", F.round("score", 6)).orderBy(F.desc("score"), "size", "network", "tree_key").limit(k)


def kth(found: DataFrame, k: int) -> float:
    """Score of the k-th tree, 0 if there are fewer."""
    row = found.select("score").orderBy(F.desc("score")).limit(k).agg(F.min("score").alias("s"), F.count("*").alias("n")).first()
    return row["s"] if row["n"] == k else 0.0


def exhaustive(prep: Prepared, k: int) -> DataFrame:
    """All networks joined over all rows, by scores alone: no ceilings and no frontier. Trees that cannot be among the best k are compared, not written out."""
    return top(factored.best_trees(prep, prep.networks, k) if prep.networks else nothing(prep), k)


def all_answers(prep: Prepared) -> DataFrame:
    """Unranked ancestor: every tree of every network, counted; all networks share all slots, fully reduced. Trees are counted link by link, not written out."""
    if not prep.networks:
        return nothing(prep).groupBy("network", "size").agg(F.count("*").alias("n_trees"))
    plan = SlotPlan.of(prep.networks, prep.best, 0.0)
    done = shared.reduce_slots(prep, plan, float("-inf"))
    return factored.counts([(net, [done.rows(plan.places[net.code][i]) for i in range(net.size)]) for net in prep.networks])


def network_cut(prep: Prepared, low: float):
    """Cut of a network evaluated alone at threshold ``low``."""
    return lambda net, i: shared.network_cut(net, i, prep.best, low)


def first_threshold(prep: Prepared, k: int) -> float:
    """k-th score among single rows: a lower bound of the final k-th score."""
    return kth(trees(prep, [n for n in prep.networks if n.size == 1]), k)


def pruned(prep: Prepared, k: int) -> DataFrame:
    """One shot: a first threshold from single rows, then all networks with filtered nodes."""
    low = first_threshold(prep, k)
    live = [n for n in prep.networks if families.potential(n, prep.best) >= low - 1e-9]
    return top(trees(prep, live, network_cut(prep, low)), k)


@dataclass
class Answer:
    top: DataFrame
    found: DataFrame
    theta: float
    bands: list[tuple[float, int]] = field(default_factory=list)  # frontier, trees found
    mark: float = 0.0  # all trees whose ceiling reaches it are found


def frontiers(prep: Prepared, nets: list[Network]) -> tuple[list[tuple[float, int]], float]:
    """(bound, rows) of all matched rows by their best bound in any network, descending, in at most 1,000 steps; and the step."""
    peak = max((families.potential(n, prep.best) for n in nets), default=0.0)
    step, bins = max(peak, 1e-9) / 1000, {}

    def one(rel):
        reach = [(n.size, rest(n, i, prep.best)) for n in nets for i, (r, mm) in enumerate(n.nodes) if mm and r == rel]
        if not reach:
            return []
        bound = F.greatest(*[(F.col("row_ceiling") + b) / s for s, b in reach], F.lit(0.0))
        return prep.matched[rel].groupBy(F.floor(bound / step).cast("int").alias("b")).count().collect()

    for rows in together([lambda r=r: one(r) for r in prep.matched]):
        for b, n in rows:
            bins[b] = bins.get(b, 0) + n
    return [(b * step, bins[b]) for b in sorted(bins, reverse=True)], step


def read_on(prep: Prepared, plan: SlotPlan, found: DataFrame | None, mark: float, least: int, band0: int = 64, growth: int = 2, headroom: float = 0.0) -> Answer:
    """Lower the frontier from ``mark`` band by band until ``least`` trees score at it or above, or all is read.

    Every band reads so many more rows, doubles the next one, and joins only trees with a row that it read. No band reads
    below the threshold so far, less ``headroom`` of it, which spares a later fall of scores another reading.
    """
    levels, _ = frontiers(prep, plan.networks)
    levels = [(low, n) for low, n in levels if low < mark]
    bands, theta, read, goal = [], 0.0, 0, band0
    if found is not None:
        theta = kth(found, least)
    for at, (bound, n) in enumerate(levels):
        if found is not None and theta * (1 - headroom) >= mark:
            break
        read += n
        if read < goal and at < len(levels) - 1 and bound > theta * (1 - headroom):
            continue
        low = 0.0 if at == len(levels) - 1 else max(bound, theta * (1 - headroom))
        live = [n for n in plan.networks if families.potential(n, prep.best) >= low - 1e-9]
        done = shared.reduce_slots(prep, plan, low, live)
        more = shared_trees(prep, plan, done, live, mark, plan.cuts(prep.best, low, live))
        found = staged(more if found is None else found.unionByName(more.join(found.select("tree_key"), "tree_key", "left_anti")), "found")
        theta, mark = kth(found, least), low
        bands.append((low, found.count()))
        goal = max(read + 1, read * growth)
    if found is None:
        found, mark = nothing(prep), 0.0
    return Answer(found, found, theta, bands, mark)


def banded(prep: Prepared, k: int | None = None, slack: int | None = None, ratio: float | None = None, seed: int = 0, band0: int = 64, growth: int = 2, headroom: float = 0.0) -> Answer:
    """Best-first in bands: lower the frontier until the (k + slack)-th score is above it."""
    k, slack = k or prep.query.k, prep.query.slack if slack is None else slack
    plan = SlotPlan.of(prep.networks, prep.best, prep.query.ratio if ratio is None else ratio, seed)
    a = read_on(prep, plan, None, float("inf"), k + slack, band0, growth, headroom)
    a.top = top(a.found, k)
    return a


def grade(found: DataFrame, theta: float) -> DataFrame:
    """top: score at the threshold or above; potential: only its ceiling is; dormant: neither."""
    return found.withColumn("grade", F.when(F.col("score") >= theta, "top").when(F.col("ceiling") >= theta, "potential").otherwise("dormant"))


def network_at_a_time(prep: Prepared, k: int) -> DataFrame:
    """Comparator: networks by descending potential, each pruned by the k-th score so far."""
    best, low = None, 0.0
    for net in sorted(prep.networks, key=lambda n: -families.potential(n, prep.best)):
        if best is not None and families.potential(net, prep.best) < low:
            break
        mine = trees(prep, [net], network_cut(prep, low))
        best = staged((mine if best is None else best.unionByName(mine)).orderBy(F.desc("score"), "size", "network", "tree_key").limit(k), "best")
        low = kth(best, k)
    return top(best, k)


def global_best_first(prep: Prepared, k: int, step: float = 0.8) -> Answer:
    """Baseline: networks by themselves; the one with the best bound is read on until its bound falls behind the next one's.

    A network's frontier is the best ceiling that its unread trees can have; it falls to that of the
    second best network, or to ``step`` of its own, and never below the k-th score so far.
    """
    frontier = {n.code: families.potential(n, prep.best) for n in prep.networks}
    by_code, best, theta, bands, begun = {n.code: n for n in prep.networks}, None, 0.0, [], set()
    while frontier:
        code = max(frontier, key=lambda c: (frontier[c], c))
        if best is not None and (frontier[code] < theta or frontier[code] <= 0):
            break
        net, high = by_code[code], frontier.pop(code)
        low = max(theta, min(max(frontier.values(), default=0.0), step * high))
        low = 0.0 if low < 1e-3 else low
        mine = trees(prep, [net], network_cut(prep, low)).where(F.col("ceiling") >= low)
        if code in begun:
            mine = mine.where(F.col("ceiling") < high)
        begun.add(code)
        best = staged((mine if best is None else best.unionByName(mine)).orderBy(F.desc("score"), "size", "network", "tree_key").limit(k), "best")
        theta = kth(best, k)
        bands.append((low, len(begun)))
        if low > 0 and low > theta:
            frontier[code] = low
    best = nothing(prep) if best is None else best
    return Answer(top(best, k), best, theta, bands, theta)


def reduced_chain(prep: Prepared, net: Network) -> list[DataFrame]:
    """Full reduction of a network by semi-joins, leaves to centre and back."""
    frames = [prep.matched[r] if m else prep.free[r] for r, m in net.nodes]
    order, todo = [], [(net.center(), -1)]
    while todo:
        i, parent = todo.pop()
        order.append((i, parent))
        todo += [(j, i) for j, _ in net.adjacent(i) if j != parent]

    def semi(i, j):
        c, p, link = next(e for e in net.edges if {e[0], e[1]} == {i, j})
        other = frames[j].select(F.col(link if j == c else "key").alias("_k")).distinct()
        frames[i] = frames[i].join(other, frames[i][link if i == c else "key"] == F.col("_k"), "left_semi")

    for i, parent in reversed(order):
        if parent >= 0:
            semi(parent, i)
    for i, parent in order:
        if parent >= 0:
            semi(i, parent)
    return frames
