"""Connected components of an edge table, without gathering edges anywhere.

Each round hooks every root to its least neighbouring root, flattens the hooks by pointer
jumping, and rewrites the edges between roots; edges inside a component vanish, so the edge
table shrinks from round to round. All state is staged in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkedrank.sources import staged


def _flat(parent: DataFrame) -> DataFrame:
    """Pointer jumping: (x, p) with p the last ancestor."""
    while True:
        up = parent.select(F.col("x").alias("p"), F.col("p").alias("q"))
        jumped = staged(parent.join(up, "p", "left").select("x", F.coalesce("q", "p").alias("p"), F.col("q").isNotNull().alias("moved")), "jump")
        parent = jumped.drop("moved")
        if jumped.where("moved").isEmpty():
            return parent


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of ``edges`` (a, b); root: the least node that it reaches.

    Self-edges and repeated edges do no harm; an empty edge table gives an empty result.
    """
    least, most = F.least("a", "b"), F.greatest("a", "b")
    left = staged(edges.where("a <> b").select(least.alias("a"), most.alias("b")).distinct(), "edges")
    roots = staged(left.select(F.col("a").alias("node")).union(left.select("b")).distinct().withColumn("root", F.col("node")), "roots")
    while not left.isEmpty():
        parent = _flat(staged(left.groupBy(F.col("b").alias("x")).agg(F.min("a").alias("p")), "hooks"))
        a = parent.select(F.col("x").alias("a"), F.col("p").alias("pa"))
        b = parent.select(F.col("x").alias("b"), F.col("p").alias("pb"))
        moved = left.join(a, "a", "left").join(b, "b", "left").select(F.coalesce("pa", "a").alias("a"), F.coalesce("pb", "b").alias("b"))
        left = staged(moved.where("a <> b").select(least.alias("a"), most.alias("b")).distinct(), "edges")
        r = parent.select(F.col("x").alias("root"), "p")
        roots = staged(roots.join(r, "root", "left").select("node", F.coalesce("p", "root").alias("root")), "roots")
    return roots


def with_class(rows: DataFrame, info: DataFrame) -> DataFrame:
    """``rows`` left-joined with ``info`` (one row per ``cls``).

    Rows without a class pass by the join. Classes with over a 10,000th of all rows (and over 1,000), of which there are
    under 10,000, are broadcast, so that no task gets all rows of a large class.
    """
    cls, more = F.col("cls"), [f for f in info.schema.fields if f.name != "cls"]
    classed = rows.where(cls.isNotNull())
    many = classed.groupBy("cls").agg(F.count("*").alias("n")).where(F.col("n") > max(1000, rows.count() // 10_000)).select("cls")
    many = F.broadcast(staged(many, "many"))
    none = rows.where(cls.isNull()).select("*", *[F.lit(None).cast(f.dataType).alias(f.name) for f in more])
    large = classed.join(F.broadcast(info.join(many, "cls", "left_semi")), "cls")
    rest = classed.join(many, "cls", "left_anti").join(info, "cls", "left")
    return none.unionByName(large).unionByName(rest)
