"""Linked schemas: relations with a key, a text and links to other relations.

A relation is a portable SQL template over the given tables, so Spark and DuckDB read the same
definition. Its columns are ``key``, ``text`` (empty where it has none) and one column per link.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from linkedrank.sources import TABLES, read_table


@dataclass(frozen=True)
class Link:
    """Foreign-key link: column ``name`` of ``child`` holds the key of ``parent``."""

    name: str
    child: str
    parent: str


@dataclass(frozen=True)
class RelationSpec:
    name: str
    sql: str
    has_text: bool = True


@dataclass(frozen=True)
class LinkedSchema:
    relations: dict[str, RelationSpec]
    links: tuple[Link, ...]
    frames: dict[str, DataFrame] = field(default_factory=dict, compare=False, hash=False)

    def neighbours(self, rel: str) -> list[tuple[Link, str, bool]]:
        """(link, other relation, whether ``rel`` is the link's child)."""
        out = [(x, x.parent, True) for x in self.links if x.child == rel]
        return out + [(x, x.child, False) for x in self.links if x.parent == rel]

    def link_columns(self, rel: str) -> list[str]:
        return [x.name for x in self.links if x.child == rel]

    def bound(self, frames: dict[str, DataFrame]) -> LinkedSchema:
        return LinkedSchema(self.relations, self.links, frames)

    def load(self, spark: SparkSession, sf_dir: str) -> LinkedSchema:
        tables = {t: read_table(spark, sf_dir, t) for t in TABLES}
        frames = {}
        for name, r in self.relations.items():
            used = {t: d for t, d in tables.items() if "{" + t + "}" in r.sql}
            frames[name] = spark.sql(r.sql, **used)
        return self.bound(frames)

    def duck(self, rel: str) -> str:
        return self.relations[rel].sql.format(**{t: t for t in TABLES})


def _schema(relations: list[tuple], links: list[tuple]) -> LinkedSchema:
    return LinkedSchema({r[0]: RelationSpec(*r) for r in relations}, tuple(Link(*x) for x in links))


# The four key columns repeat at times; with the price in cents they name a row, by projection alone.
LINE_ID = (
    "concat_ws('-', CAST(l_orderkey AS STRING), CAST(l_partkey AS STRING), CAST(l_suppkey AS STRING), CAST(l_linenumber AS STRING), "
    "CAST(CAST(round(l_extendedprice * 100) AS BIGINT) AS STRING))"
)
TRADE = _schema(
    [
        ("region", "SELECT r_regionkey AS key, r_name AS text FROM {region}"),
        ("nation", "SELECT n_nationkey AS key, n_name AS text, n_regionkey AS nation_region FROM {nation}"),
        ("customer", "SELECT c_custkey AS key, concat_ws(' ', c_name, c_mktsegment) AS text, c_nationkey AS customer_nation FROM {customer}"),
        ("supplier", "SELECT s_suppkey AS key, s_name AS text, s_nationkey AS supplier_nation FROM {supplier}"),
        ("part", "SELECT p_partkey AS key, concat_ws(' ', p_name, p_brand, p_type) AS text FROM {part}"),
        ("orders", "SELECT o_orderkey AS key, o_orderpriority AS text, o_custkey AS orders_customer FROM {orders}"),
        ("lineitem", f"SELECT {LINE_ID} AS key, '' AS text, l_orderkey AS line_order, l_partkey AS line_part, l_suppkey AS line_supplier FROM {{lineitem}}", False),
    ],
    [("nation_region", "nation", "region"), ("customer_nation", "customer", "nation"), ("supplier_nation", "supplier", "nation"),
     ("orders_customer", "orders", "customer"), ("line_order", "lineitem", "orders"), ("line_part", "lineitem", "part"), ("line_supplier", "lineitem", "supplier")],
)
_D = "(SELECT count(*) FROM {documents})"
LIBRARY = _schema(
    [
        ("documents", "SELECT doc_id AS key, coalesce(text, '') AS text, doc_id % (SELECT count(*) FROM {pages}) AS doc_page FROM {documents}"),
        ("author", "SELECT c_custkey AS key, concat_ws(' ', c_name, c_mktsegment, concat('na', CAST(c_custkey % 250 AS STRING)), concat('nb', CAST(c_custkey % 143 AS STRING)), "
                   "concat('nc', CAST(c_custkey % 77 AS STRING)), concat('nd', CAST(c_custkey % 33 AS STRING))) AS text FROM {customer}"),
        ("wrote", f"SELECT event_id AS key, '' AS text, user_id AS wrote_by, event_id % {_D} AS wrote_doc FROM {{events}}", False),
        ("cites", f"SELECT event_id AS key, '' AS text, event_id % {_D} AS citing, (event_id * 31 + 7) % {_D} AS cited FROM {{events}} WHERE event_type = 'view' AND event_id % {_D} <> (event_id * 31 + 7) % {_D}", False),
        ("labels", "SELECT doc_id AS key, '' AS text, doc_id AS label_doc FROM {labels}", False),
    ],
    [("wrote_by", "wrote", "author"), ("wrote_doc", "wrote", "documents"), ("citing", "cites", "documents"), ("cited", "cites", "documents"), ("label_doc", "labels", "documents")],
)
SAMPLE = _schema(
    [("papers", ""), ("authors", ""), ("writes", "", False)],
    [("w_author", "writes", "authors"), ("w_paper", "writes", "papers")],
)
# The worked example's links (write, author, paper).
SAMPLE_WRITES = [("w1", "a1", "p2"), ("w2", "a2", "p1"), ("w3", "a3", "p3"), ("w4", "a1", "p4"), ("w5", "a5", "p5"), ("w6", "a3", "p4"), ("w7", "a2", "p2"), ("w8", "a2", "p5")]
# Row -> (occurrences of its query word, text length).
SAMPLE_MATCHES = {"p1": (1, 88), "p2": (3, 28), "p5": (1, 83), "a1": (1, 10), "a3": (1, 22), "a5": (1, 23)}
# Relation -> (rows, rows with the word, mean text length).
SAMPLE_STATS = {"papers": (150, 3, 57.8), "authors": (170, 3, 14.6)}
