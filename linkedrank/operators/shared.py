"""Execution of the shared slot graph.

A slot's reduced set holds the rows of its relation (read matched rows, or all free rows) that have a
partner in the reduced set of every child slot. The sets of all slots of one relation and depth are one staged
table: a row carries a bit per slot. A depth is computed from the tables below it with one join per link
that its slots use, whatever the number of slots or networks; a subtree that several networks of a family
share is thus reduced once. Networks are joined from the reduced sets, centre first, so that no partial tree dies.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkedrank.plans import families, slots
from linkedrank.plans.networks import Network
from linkedrank.sources import staged, together

WORD = 62  # bits of a mask column


def rest(net: Network, i: int, best: dict[str, float]) -> float:
    """Best ceilings of the network's matched nodes other than i."""
    return sum(best[rel] for j, (rel, m) in enumerate(net.nodes) if m and j != i)


def network_cut(net: Network, i: int, best: dict[str, float], low: float) -> float:
    """Least row ceiling at node i of a tree whose ceiling reaches ``low``."""
    return low * net.size - rest(net, i, best) - 1e-9


@dataclass
class SlotPlan:
    """Slots of a set of networks under a family assignment."""

    networks: list[Network]
    family: dict[str, int]
    graph: dict[tuple[int, str], slots.Slot]
    places: dict[str, dict[int, tuple[int, str]]]  # network -> node -> slot

    @classmethod
    def of(cls, networks: list[Network], best: dict[str, float], ratio: float, seed: int = 0) -> SlotPlan:
        family = families.cluster(networks, best, ratio, seed)
        return cls(networks, family, slots.build(networks, family), {n.code: slots.places(n, family[n.code]) for n in networks})

    def cuts(self, best: dict[str, float], low: float, live: list[Network] | None = None) -> dict[tuple[int, str], float]:
        """Cut of each matched slot: the least cut of the (live) networks that share it."""
        out: dict[tuple[int, str], float] = {}
        for net in self.networks if live is None else live:
            for i, slot in self.places[net.code].items():
                if net.nodes[i][1]:
                    out[slot] = min(out.get(slot, float("inf")), network_cut(net, i, best, low))
        return out


@dataclass
class Reduced:
    """Reduced sets: one staged table per (relation, depth, group), and the bit of each slot in it."""

    tables: dict[tuple[str, int, int], DataFrame] = field(default_factory=dict)
    bit: dict[tuple[int, str], tuple[tuple[str, int, int], int]] = field(default_factory=dict)  # slot -> table, number
    selections: int = 0  # edges of slots that asked for partners
    joins: int = 0  # joins that were run for them

    def rows(self, slot: tuple[int, str]) -> DataFrame:
        table, n = self.bit[slot]
        t = self.tables[table]
        return t.where(has(F.col(f"m{n // WORD}"), n)).drop(*[c for c in t.columns if c.startswith("m") and c[1:].isdigit()])


def has(mask: Column, n: int) -> Column:
    return mask.bitwiseAND(F.lit(1 << (n % WORD)).cast("long")) != 0


def all_rows(prep, rel: str, kinds: set[bool]) -> DataFrame:
    """Rows of a relation with ``matched``; free rows score 0."""
    out = []
    if True in kinds and rel in prep.matched:
        out.append(prep.matched[rel].withColumn("matched", F.lit(True)))
    if False in kinds:
        out.append(prep.free[rel].withColumn("matched", F.lit(False)).withColumn("row_score", F.lit(0.0)).withColumn("row_ceiling", F.lit(0.0)))
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), out)


def _support(prep, done: Reduced, label: str, wanted: set[tuple[int, str]]) -> tuple[DataFrame, dict]:
    """(at, masks): which wanted child slots the rows joined to ``at`` are in, and the column and number of each."""
    link, up = label[:-1], label.endswith("^")
    column, parts, masks = {}, [], []
    for table in sorted({done.bit[s][0] for s in wanted}):
        depth = f"{table[1]}_{table[2]}"
        numbers = sorted({done.bit[s][1] for s in wanted if done.bit[s][0] == table})
        words = sorted({n // WORD for n in numbers})
        column |= {s: (f"{label}{depth}_{done.bit[s][1] // WORD}", done.bit[s][1]) for s in wanted if done.bit[s][0] == table}
        t = done.tables[table]
        t = t.where(reduce(lambda a, b: a | b, [has(F.col(f"m{n // WORD}"), n) for n in numbers]))
        parts.append(t.select(F.col("key" if up else link).alias(f"{label}at"), *[F.col(f"m{w}").alias(f"{label}{depth}_{w}") for w in words]))
        masks += [f"{label}{depth}_{w}" for w in words]
    out = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), parts)
    if not up or len(parts) > 1:  # several rows may share ``at``
        out = out.groupBy(f"`{label}at`").agg(*[F.bit_or(f"`{m}`").alias(m) for m in masks])
    return out, column


def _table(prep, plan: SlotPlan, done: Reduced, rel: str, mine: list, cuts: dict) -> DataFrame:
    rows = all_rows(prep, rel, {plan.graph[s].matched for s in mine})
    own_columns = rows.columns
    needs = {s: {(label, (s[0], code)) for code, label in plan.graph[s].children} for s in mine}
    column: dict = {}
    for label in sorted({x for n in needs.values() for x, _ in n}):
        wanted = {c for n in needs.values() for x, c in n if x == label}
        support, at = _support(prep, done, label, wanted)
        done.joins += 1
        column |= {(label, c): v for c, v in at.items()}
        own = F.col(label[:-1]) if label.endswith("^") else F.col("key")
        every = all(any(x == label for x, _ in n) for n in needs.values())
        rows = rows.join(support, own == F.col(f"`{label}at`"), "inner" if every else "left")
    words = [F.lit(0).cast("long")] * (-(-len(mine) // WORD))
    for n, s in enumerate(mine):
        slot = plan.graph[s]
        test = F.col("matched") == F.lit(slot.matched)
        if slot.matched:
            test = test & (F.col("row_ceiling") >= cuts[s])
        for label, child in needs[s]:
            name, number = column[label, child]
            test = test & F.coalesce(has(F.col(f"`{name}`"), number), F.lit(False))
        words[n // WORD] = words[n // WORD].bitwiseOR(F.when(test, F.lit(1 << (n % WORD)).cast("long")).otherwise(F.lit(0).cast("long")))
    rows = rows.select(*own_columns, *[w.alias(f"m{k}") for k, w in enumerate(words)])
    return rows.where(reduce(lambda a, b: a | b, [F.col(f"m{k}") != 0 for k in range(len(words))]))


def reduce_slots(prep, plan: SlotPlan, low: float, live: list[Network] | None = None, joint: bool = True) -> Reduced:
    """Reduced sets of all slots of the live networks, where matched rows are read down to ``low``.

    joint: partners along a link are fetched once for all slots of a relation and depth; else by every slot for itself.
    """
    live = plan.networks if live is None else live
    cuts, used = plan.cuts(prep.best, low, live), {s for n in live for s in plan.places[n.code].values()}
    done = Reduced()
    for depth in sorted({plan.graph[s].depth for s in used}):
        groups: dict[tuple[str, int, int], list] = {}
        for s in sorted(used):
            if plan.graph[s].depth == depth:
                groups.setdefault((plan.graph[s].rel, depth, 0 if joint else len(groups)), []).append(s)
                done.selections += len(plan.graph[s].children)
        names = list(groups)
        tables = together([lambda t=t: staged(_table(prep, plan, done, t[0], groups[t], cuts), f"slots-{t[0]}-{depth}") for t in names])
        for name, t in zip(names, tables):
            done.tables[name] = t
            done.bit |= {s: (name, n) for n, s in enumerate(groups[name])}
    return done


def read_ratio(prep, plan: SlotPlan, low: float) -> float:
    """Read rows over all rows of the matched slots, when matched rows are read down to ``low``."""
    cuts, read, total = plan.cuts(prep.best, low), 0, 0
    for rel, m in prep.matched.items():
        own = [cuts[s] for s, slot in plan.graph.items() if slot.matched and slot.rel == rel]
        row = m.agg(F.count("*").alias("n"), *[F.sum((F.col("row_ceiling") >= c).cast("long")).alias(f"r{i}") for i, c in enumerate(own)]).first()
        read, total = read + sum(row[f"r{i}"] or 0 for i in range(len(own))), total + row["n"] * len(own)
    return read / total if total else 0.0
