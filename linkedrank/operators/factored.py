"""Trees of whole networks, counted or ranked without writing all of them down.

A network's join is a product of its nodes' rows along links. A count sums that product link by link, so that a
hub with n rows costs n and not n to the number of its neighbours. Rows that may not be in a tree twice are taken out by
inclusion and exclusion. For the best trees every row carries the best sum of scores of the joined rows below it; the
trees of all rows are compared by it, and only those that can be among the best are written out.
"""

from __future__ import annotations

from collections import Counter
from functools import reduce
from math import factorial

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkedrank.plans.networks import Network
from linkedrank.sources import staged

DIGITS = 6  # scores are ranked by so many decimals


def mergers(net: Network) -> Counter:
    """Ways to let nodes of one relation hold one row, with the weight of each in the number of trees of distinct rows.

    A way is a tuple with the block of each node; ways that a symmetry of the network turns into each other count as one.
    """
    ways: list[list[int]] = [[]]
    for i, (rel, _) in enumerate(net.nodes):
        ways = [[*w, b] for w in ways for b in [*sorted({w[j] for j in range(i) if net.nodes[j][0] == rel}), i]]
    out: Counter = Counter()
    for w in ways:
        weight = 1
        for n in Counter(w).values():
            weight *= (-1) ** (n - 1) * factorial(n - 1)
        out[min(_named([w[i] for i in perm]) for perm in [range(net.size), *net.automorphisms])] += weight
    return out


def _named(blocks: list[int]) -> tuple[int, ...]:
    """Blocks by the first node in each."""
    return tuple(blocks.index(b) for b in blocks)


Factor = tuple[frozenset, DataFrame]  # variables, and a table of them (columns v0..) with n, the weight of the row


def _factors(net: Network, frames: list[DataFrame], way: tuple[int, ...]) -> list[Factor]:
    """A table per node: its key and the keys that it links to, as the variables of their blocks."""
    relations, out = Counter(rel for rel, _ in net.nodes), []
    for i, f in enumerate(frames):
        if relations[net.nodes[i][0]] > 1:
            f = f.where(F.col("key").isNotNull())
        columns: dict[int, Column] = {way[i]: F.col("key")}
        for c, p, link in net.edges:
            if c == i:
                if way[p] in columns:
                    f = f.where(F.col(link) == columns[way[p]])
                columns.setdefault(way[p], F.col(link))
        out.append((frozenset(columns), f.select(*[x.alias(f"v{v}") for v, x in columns.items()], F.lit(1).cast("long").alias("n"))))
    return out


def _summed(f: Factor) -> DataFrame:
    return f[1].groupBy(*[f"v{v}" for v in sorted(f[0])]).agg(F.sum("n").alias("n"))


def _product(factors: list[Factor]) -> DataFrame:
    """One row: n summed over all values of the variables; a variable is summed away once its tables are joined."""
    while True:
        uses = Counter(v for own, _ in factors for v in own)
        factors = [(left, d.select(*[f"v{v}" for v in sorted(left)], "n")) for own, d in factors for left in [frozenset(v for v in own if uses[v] > 1)]]
        open_ = {v for own, _ in factors for v in own}
        if not open_:
            return factors[0][1].agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
        v = min(open_, key=lambda v: (len(frozenset().union(*[own for own, _ in factors if v in own])), v))
        head, *others = sorted((f for f in factors if v in f[0]), key=lambda f: -len(f[0]))
        own, out = head[0], _summed(head) if len(head[0]) == 1 else head[1]
        for f in others:
            out = out.join(_summed(f).withColumnRenamed("n", "m"), [f"v{x}" for x in sorted(own & f[0])])
            own = own | f[0]
            out = out.select(*[f"v{x}" for x in sorted(own)], (F.col("n") * F.col("m")).alias("n"))
        factors = [f for f in factors if v not in f[0]] + [(own, out)]


def counts(nets: list[tuple[Network, list[DataFrame]]]) -> DataFrame:
    """network, size, n_trees of the networks that have trees; a network comes with the rows of its nodes."""
    parts = []
    for net, frames in nets:
        for way, weight in mergers(net).items():
            if weight:
                parts.append(_product(_factors(net, frames, way)).select(
                    F.lit(net.code).alias("network"), F.lit(net.size).alias("size"), F.lit(1 + len(net.automorphisms)).alias("copies"), (F.col("n") * F.lit(weight)).alias("n")))
    total = reduce(DataFrame.unionByName, parts).groupBy("network", "size", "copies").agg(F.sum("n").alias("n"))
    return total.where("n > 0").select("network", "size", F.expr("n div copies").alias("n_trees"))


class Subtrees:
    """Rows of each rooted subtree that join all the way down, with ``best``: the highest sum of scores of such a join.

    ``best`` lets a row occur twice in a join, so it is never below the best tree's sum, and equal to it where no relation
    occurs twice. ``b0``.. are the bests of the distinct children, in the order of ``kinds``. Equal subtrees are one table.
    """

    def __init__(self, prep):
        self.prep, self.known = prep, {}

    def kinds(self, net: Network, i: int, parent: int) -> list[tuple[str, str]]:
        return sorted({(label, net.rooted(j, i)[0]) for j, label in net.adjacent(i) if j != parent})

    def rows(self, net: Network, i: int, parent: int = -1) -> DataFrame:
        code = net.rooted(i, parent)[0]
        if code not in self.known:
            rel, matched = net.nodes[i]
            out = self.prep.matched[rel] if matched else self.prep.free[rel].withColumn("row_score", F.lit(0.0))
            out = out.withColumn("best", F.col("row_score"))
            kids = [(label, net.rooted(j, i)[0], j) for j, label in net.adjacent(i) if j != parent]
            for at, kind in enumerate(self.kinds(net, i, parent)):
                same = [j for label, c, j in kids if (label, c) == kind]
                link, up = kind[0][:-1], kind[0].endswith("^")
                below = self.rows(net, same[0], i).groupBy(F.col("key" if up else link).alias("_at")).agg(F.max("best").alias(f"b{at}"))
                out = out.join(below, F.col(link if up else "key") == F.col("_at")).drop("_at")
                out = out.withColumn("best", F.col("best") + F.col(f"b{at}") * len(same))
            self.known[code] = staged(out, f"subtree-{rel}") if kids else out
        return self.known[code]

    def trees(self, net: Network, low: float) -> DataFrame:
        """All trees of the network with a score of at least ``low``, root first; a partial tree stays only if its best completion reaches it."""
        from linkedrank.operators.evaluate import as_trees, joined

        root, need = net.center(), low * net.size - 1e-9
        named = lambda d, i: d.select(*[F.col(c).alias(f"n{i}_{c}") for c in d.columns])
        first = self.rows(net, root)
        out, columns, placed, todo = named(first, root).withColumn("total", F.col(f"n{root}_best")).where(F.col("total") >= need), {root: first.columns}, {root}, [(root, -1)]
        while todo:
            i, parent = todo.pop()
            kinds = self.kinds(net, i, parent)
            for j, label in net.adjacent(i):
                if j == parent:
                    continue
                rows, at = self.rows(net, j, i), kinds.index((label, net.rooted(j, i)[0]))
                c, p, link = next(e for e in net.edges if {e[0], e[1]} == {i, j})
                out = out.join(named(rows, j), joined(net, placed, j, c, p, link))
                out = out.withColumn("total", F.col("total") - F.col(f"n{i}_b{at}") + F.col(f"n{j}_best")).where(F.col("total") >= need)
                placed.add(j)
                columns[j] = rows.columns
                todo.append((j, i))
        return as_trees(net, out, [columns[i] for i in range(net.size)])


def best_trees(prep, nets: list[Network], k: int) -> DataFrame:
    """Trees of the networks, with all that are among the k best by rounded score, size, network and key.

    All networks are joined over all rows. The k-th score comes from the best trees of the roots' rows, in networks where no
    relation occurs twice: those are k trees, so no tree below the k-th of them is wanted, and none that only equals
    it in a network behind those that have k such trees.
    """
    from linkedrank.operators.evaluate import kth

    sub, nets = Subtrees(prep), sorted(nets, key=lambda n: (n.size, n.code))
    for net in nets:
        sub.rows(net, net.center())
    scores = [sub.rows(n, n.center()).select(F.lit(at).alias("at"), F.round(F.col("best") / n.size, DIGITS).alias("score"))
              for at, n in enumerate(nets) if len({rel for rel, _ in n.nodes}) == n.size]
    low, reach = 0.0, {}
    if scores:
        scores = reduce(DataFrame.unionByName, scores)
        low = kth(scores, k)
        reach = {r["at"]: r["count"] for r in scores.where(F.col("score") >= low).groupBy("at").count().collect()}
    half, out = 0.5 * 10.0**-DIGITS, []
    for at, net in enumerate(nets):
        full = sum(n for x, n in reach.items() if x < at) >= k
        out.append(sub.trees(net, low + half if full else low - half))
    return reduce(DataFrame.unionByName, out)
