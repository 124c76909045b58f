"""Partners of changed rows: one join per link and path, shared by every network and query that asks.

A path is a sequence of links walked from the changed rows. Its partners are fetched once, by a join of the path
before it with the relation that the link leads to; whether a partner is matched, read or free is tested
afterwards by each network that asks. Fetched partners are persisted, which is the barrier that keeps the
optimizer from pushing those tests below the join again; lost executors cost a recomputation, not rows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkedrank.plans.catalog import Link, LinkedSchema


class PartnerCache:
    """``selections`` counts what was asked for, ``joins`` what was run.

    rows(rel): all rows of a relation, with key, links and what the askers need; by default those of the schema.
    worth(path): filter that holds for every row of a path that some asker can use, or None.
    """

    def __init__(self, schema: LinkedSchema, enabled: bool = True, rows: Callable[[str], DataFrame] | None = None, worth: Callable[[tuple], Column | None] | None = None):
        self.schema, self.enabled, self.known = schema, enabled, {}
        self.rows = rows or (lambda rel: schema.frames[rel].select("key", *schema.link_columns(rel)))
        self.worth, self.selections, self.joins = worth or (lambda path: None), 0, 0
        self.links = {x.name: x for x in schema.links}

    def along(self, rel: str, rows: DataFrame, link: Link, name: str = "delta") -> DataFrame:
        """(source, key) partners of ``rows`` (key and links of ``rel``) along a link."""
        path = (f"{link.name}{'^' if rel == link.child else 'v'}",)
        return self.edges(name, rows, path).select("source", "key")

    def edges(self, name: str, start: DataFrame, path: tuple[str, ...]) -> DataFrame:
        """Rows at the end of a path from ``start``, with the key that they were reached from as ``source``."""
        self.selections += 1
        if not self.enabled:
            return self._join(start if len(path) == 1 else self._ends(self._fresh(start, path[:-1])), path)
        for n in range(1, len(path) + 1):
            if (name, path[:n]) not in self.known:
                before = start if n == 1 else self._ends(self.known[name, path[: n - 1]])
                self.known[name, path[:n]] = self._join(before, path[:n]).persist()
        return self.known[name, path]

    def _fresh(self, start: DataFrame, path: tuple[str, ...]) -> DataFrame:
        return self._join(start if len(path) == 1 else self._ends(self._fresh(start, path[:-1])), path)

    def _ends(self, edges: DataFrame) -> DataFrame:
        return edges.drop("source").dropDuplicates(["key"])

    def _join(self, before: DataFrame, path: tuple[str, ...]) -> DataFrame:
        self.joins += 1
        link, up, worth = self.links[path[-1][:-1]], path[-1].endswith("^"), self.worth(path)
        other = self.rows(link.parent if up else link.child)
        other = other if worth is None else other.where(worth)
        own = before.select(F.col("key").alias("source"), *([F.col(link.name).alias("_to")] if up else []))
        return own.join(other, F.col("_to") == F.col("key")).drop("_to") if up else own.join(other, F.col("source") == F.col(link.name))

    def within(self, partners: DataFrame, members: DataFrame) -> DataFrame:
        """The membership test of one asker."""
        return partners.join(members.select("key"), "key", "left_semi")

    def expire(self) -> None:
        """A change's partners are of no use after it."""
        for d in self.known.values():
            d.unpersist()
        self.known.clear()
