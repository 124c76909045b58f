"""Operator 10 (native): time-varying mixing of sources to target weights.

A source's share of the training run is its target; *when* it is read follows a weight
schedule, linear in training time t in [0, 1]. Integrating the schedule gives the share of
the source's demand that is used up by time t; inverting that integral turns a document's
place in its source's token stream into a training position, and documents are range-sorted
by position.

The place in the stream is a prefix sum in a stable random order (MD5 of the id). It is
computed over two levels of hash buckets, so that no task ever holds a source: documents are
summed within 1/65,536 of their source, and bucket totals within 256 rows.

Edge cases: a null text has size 0; a null source is a source of its own, last in order;
sources of size 0 get target 0; repeated rows and equal ids are separate documents whose
order among themselves follows their size; an empty table gives an empty result. Only id, text
and source are read (``mix``); other columns pass through untouched (``mixed_documents``).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linkedrank.sources import read_table, staged

SPACE = r"[\x20\x09-\x0D]+"
WEIGHTS = (5, 2, 1)
RAMPS = ((1.5, 0.5), (1.0, 1.0), (0.5, 1.5))  # weight at t=0 and t=1, repeating like WEIGHTS
MOST = 3


def word_count(text: Column) -> Column:
    return F.coalesce(F.size(F.array_remove(F.split(text, SPACE), "")), F.lit(0)).cast("long")


def _cyclic(values, place: Column) -> Column:
    at = F.pmod(place, F.lit(len(values)))
    out = F.lit(values[-1])
    for i, v in enumerate(values[:-1]):
        out = F.when(at == i, F.lit(v)).otherwise(out)
    return out


def source_targets(sizes: DataFrame, weights=WEIGHTS, most: int = MOST) -> DataFrame:
    """Target of each source: its weight's share of all sizes, at most ``most`` times its size.

    ``sizes``: (source, no_source, size). Water-filling in closed form: sources in the order
    of cap over weight; the level is taken at the first source that stays under its cap.
    """
    s = sizes.groupBy("no_source", "source").agg(F.sum("size").alias("source_size"))
    s = s.withColumn("place", F.row_number().over(Window.orderBy("no_source", "source")) - 1)
    s = s.withColumn("weight", _cyclic(weights, F.col("place")).cast("long")).withColumn("cap", F.col("source_size") * most)
    by_need = Window.orderBy(F.col("cap") / F.col("weight"), "place")
    everything = Window.partitionBy()
    s = s.withColumn("total", F.sum("source_size").over(everything))
    s = s.withColumn("left", F.col("total") - F.sum("cap").over(by_need.rowsBetween(Window.unboundedPreceding, 0)) + F.col("cap"))
    s = s.withColumn("open", F.sum("weight").over(by_need.rowsBetween(0, Window.unboundedFollowing)))
    s = s.withColumn("under", F.col("left") * F.col("weight") <= F.col("cap") * F.col("open"))
    level = F.min_by(F.struct("left", "open"), F.struct(F.col("cap") / F.col("weight"), F.col("place"))).over(everything)
    s = s.withColumn("level", F.when(F.max("under").over(everything), F.min_by(
        F.struct("left", "open"), F.when(F.col("under"), F.struct(F.col("cap") / F.col("weight"), F.col("place")))).over(everything)).otherwise(level))
    full = F.col("cap").cast("double")
    share = (F.col("level.left") * F.col("weight")).cast("double") / F.col("level.open")
    return s.select("no_source", "source", "source_size", "place", F.least(full, share).alias("target"))


def position(share: Column, place: Column, ramps=RAMPS) -> Column:
    """Training time at which ``share`` of a source's demand is used up (inverse integral)."""
    a, b = _cyclic([r[0] for r in ramps], place), _cyclic([r[1] for r in ramps], place)
    area = (a + b) / 2
    bent = (F.sqrt(a * a + F.lit(2.0) * (b - a) * share * area) - a) / (b - a)
    return F.when(a == b, share).otherwise(bent)


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
        carry: dict[str, Column] | None = None, **shape) -> DataFrame:
    """Per document: size, source_size, target, passes, taken and its place in its source's stream."""
    carry = carry or {}
    d = docs.select(
        docs[id_col].alias("doc_id"), *[c.alias(n) for n, c in carry.items()],
        docs[source_col].isNull().alias("no_source"), F.coalesce(docs[source_col].cast("string"), F.lit("")).alias("source"),
        word_count(docs[text_col]).alias("size"), F.md5(F.coalesce(docs[id_col].cast("string"), F.lit(""))).alias("key"),
    )
    d = staged(d.withColumn("hi", F.substring("key", 1, 2)).withColumn("lo", F.substring("key", 3, 2)), "mix-sizes")
    src, box = ["no_source", "source"], ["no_source", "source", "hi", "lo"]
    fine = staged(d.groupBy(*box).agg(F.sum("size").alias("n")), "mix-buckets")
    targets = source_targets(fine.withColumnRenamed("n", "size"), **shape)
    before = lambda w: F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")
    coarse = fine.groupBy(*src, "hi").agg(F.sum("n").alias("n"))
    coarse = coarse.select(*src, "hi", before(Window.partitionBy(*src).orderBy("hi")).alias("before_hi"))
    fine = fine.select(*box, before(Window.partitionBy(*src, "hi").orderBy("lo")).alias("before_lo"))
    offsets = fine.join(coarse, [*src, "hi"]).join(targets, src)
    own = Window.partitionBy(*box).orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    d = d.withColumn("cum", F.sum("size").over(own) - F.col("size")).join(offsets, box)
    d = d.withColumn("cum", F.col("cum") + F.col("before_hi") + F.col("before_lo"))
    d = d.withColumn("take", F.floor(F.col("target") + 0.5).cast("long"))
    d = d.withColumn("passes", F.when(F.col("source_size") > 0, F.floor(F.col("take") / F.col("source_size"))).otherwise(0).cast("long"))
    rest = F.col("take") - F.col("passes") * F.col("source_size") - F.col("cum")
    d = d.withColumn("part", F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), rest)))
    d = d.withColumn("taken", F.col("passes") * F.col("size") + F.col("part"))
    return d.select("doc_id", *carry, "size", "source_size", "target", "taken", "passes", "part", "cum", "take", "place", "key")


def copy_position(which: Column, ramps=RAMPS) -> Column:
    """Training position of a document's copy in pass ``which`` (from 0): where it starts."""
    share = (which * F.col("source_size") + F.col("cum")).cast("double") / F.col("take")
    return position(F.least(share, F.lit(1.0)), F.col("place"), ramps)


def mixed_documents(docs: DataFrame, **shape) -> DataFrame:
    """The rows of ``docs`` in training order, one row per pass. Documents stay whole: the one
    at the end of a source's last pass is in it if at least half of its words are taken."""
    row = {"row": F.struct(*[docs[c] for c in docs.columns])}
    m = mix(docs, carry=row, **shape)
    copies = (F.col("passes") + F.when(F.col("part") * 2 >= F.greatest(F.col("size"), F.lit(1)), 1).otherwise(0)).cast("int")
    m = m.where(copies > 0).withColumn("pass", F.explode(F.sequence(F.lit(0), copies - 1)))
    return m.withColumn("at", copy_position(F.col("pass"))).orderBy("at", "key", "pass").select("row.*")


def op10(spark, sf_dir: str) -> DataFrame:
    m = mix(read_table(spark, sf_dir, "documents"))
    m = m.withColumn("first_position", F.when(F.col("taken") > 0, F.round(copy_position(F.lit(0)), 6)))
    return m.select("doc_id", "size", "source_size", "target", "taken", "first_position").orderBy("first_position", "doc_id")


def oracle_sql() -> str:
    cyc = lambda v: "CASE (place % 3) " + " ".join(f"WHEN {i} THEN {x}" for i, x in enumerate(v)) + " END"
    a, b = cyc([f"{r[0]}::DOUBLE" for r in RAMPS]), cyc([f"{r[1]}::DOUBLE" for r in RAMPS])
    return f"""
WITH d AS (SELECT doc_id, source, md5(CAST(doc_id AS VARCHAR)) AS key,
    CAST(CASE WHEN text IS NULL THEN 0 ELSE len(list_filter(regexp_split_to_array(text, '[ \\t\\n\\x0B\\f\\r]+'), lambda x: x <> '')) END AS BIGINT) AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS place FROM d GROUP BY source),
w AS (SELECT *, {cyc(WEIGHTS)} AS weight, source_size * {MOST} AS cap FROM s),
f AS (SELECT *, sum(source_size) OVER () - sum(cap) OVER (ORDER BY cap / weight, place) + cap AS lft,
    sum(weight) OVER (ORDER BY cap / weight, place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS opn FROM w),
l AS (SELECT lft, opn FROM f WHERE lft * weight <= cap * opn ORDER BY cap / weight, place LIMIT 1),
t AS (SELECT source, source_size, place, least(CAST(cap AS DOUBLE), CAST(l.lft * weight AS DOUBLE) / CAST(l.opn AS DOUBLE)) AS target FROM f, l),
c AS (SELECT d.doc_id, d.size, t.source_size, t.target, t.place, CAST(floor(target + 0.5) AS BIGINT) AS take,
    CAST(sum(size) OVER (PARTITION BY d.source ORDER BY key, doc_id, size ROWS UNBOUNDED PRECEDING) - size AS BIGINT) AS cum
    FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
p AS (SELECT *, CASE WHEN source_size > 0 THEN take // source_size ELSE 0 END AS passes FROM c),
q AS (SELECT *, passes * size + greatest(0, least(size, take - passes * source_size - cum)) AS taken, {a} AS a, {b} AS b,
    least(1.0::DOUBLE, CAST(cum AS DOUBLE) / CAST(take AS DOUBLE)) AS u FROM p)
SELECT doc_id, size, source_size, target, CAST(taken AS BIGINT) AS taken,
  CASE WHEN taken > 0 THEN round(CASE WHEN a = b THEN u ELSE (sqrt(a * a + 2.0::DOUBLE * (b - a) * u * ((a + b) / 2)) - a) / (b - a) END, 6) END AS first_position
FROM q"""
