"""Operator 3: near-duplicate vectors by randomised-rotation binary codes.

Each unit vector is turned by a random rotation; the signs are its code, and the stored
correction factor is the mean product of a rotated vector with its sign vector. With s the
sign vector of x, <s, y> / <s, x> is an unbiased estimate of the cosine of x and y over the
rotation, and its error is bounded with high probability by the spread that the correction
factor leaves. Vectors that share a key of a hash table are compared: the estimate plus its bound rules
pairs out; the rest is recomputed exactly in double precision. A pair counts in the first table that it shares only.

A key is made of a few digits, each the place and sign of the largest of some coordinates in a rotation of its own. It
grows with log2 of the number of vectors, so that unrelated vectors rarely meet, and the number of
tables is set so that a pair at the threshold shares a key with probability RECALL. Keys and row numbers are dealt
as packed arrays, and only rows that share a key carry their vector on. Bins of many buckets are compared at a time.
Equal vectors are one class; large buckets are compared block against block; a bin returns one sum per vector and a
spanning set of its links, so groups never emit their pairs.

Edge cases: null vectors, zero vectors and vectors with null or non-finite components link with
nothing; vectors of different lengths are never compared; repeated rows count as other
vectors; rows with a null id take part in link counts but name no component unless alone;
an empty table gives an empty result; labels and extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkedrank.llm.components import components, with_class
from linkedrank.sources import read_table, staged

THRESHOLD, RECALL, SURE, BLOCK = 0.95, 0.9995, 4.5, 2048
DIGIT_BITS, SPARE_BITS, KEY_BITS = 6, 3, 32
SMALL, PAIRS = 32, 65536  # rows of a bucket whose pairs are listed; pairs at a time
BIN_ROWS, BIN_KEYS, HELD_KEYS = 16_384, 1_000_000, 2_000_000  # of a bin of vectors, of a bin of keys, of keys before they are dealt
_rotations: dict = {}


def rotations(dim: int, many: int, most: int) -> np.ndarray:
    """``many`` random sets of ``most`` orthogonal directions side by side: (dim, many * most)."""
    if (dim, many, most) not in _rotations:
        rng = np.random.default_rng([dim, 77])
        _rotations[dim, many, most] = np.concatenate([np.linalg.qr(rng.standard_normal((dim, most)))[0] for _ in range(many)], axis=1)
    return _rotations[dim, many, most]


def shared_digit(dim: int, most: int, cosine: float) -> float:
    """Probability that two vectors of that cosine share a digit: a lower estimate by simulation."""
    n, r = max(2000, min(40_000, 4_000_000 // dim)), np.random.default_rng(5)
    x, z = (r.standard_normal((n, dim)) for _ in range(2))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    z -= (z * x).sum(axis=1, keepdims=True) * x
    z /= np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-300)
    y = cosine * x + math.sqrt(1 - cosine * cosine) * z
    p = float((_digits(x[:, None, :most]) == _digits(y[:, None, :most])).mean())
    return p - 3 * math.sqrt(p * (1 - p) / n)


def plan(n: int, dim: int, threshold: float = THRESHOLD, recall: float = RECALL) -> tuple[int, int, int]:
    """Coordinates of a digit, digits of a key and number of tables for n vectors."""
    bits = min(KEY_BITS, max(8, math.ceil(math.log2(max(n, 2))) + SPARE_BITS))
    digits = max(math.ceil(bits / DIGIT_BITS), math.ceil(bits / math.log2(2 * dim)))
    most = min(dim, math.ceil(2 ** (bits / digits) / 2))
    same = shared_digit(dim, most, threshold) ** digits
    return most, digits, max(1, math.ceil(math.log(1 - recall) / math.log1p(-min(same, 0.999))))


def _digits(turned: np.ndarray) -> np.ndarray:
    """Place and sign of the largest coordinate along the last axis."""
    high, low = turned.argmax(axis=-1), turned.argmin(axis=-1)
    top, bottom = (np.take_along_axis(turned, k[..., None], -1)[..., 0] for k in (high, low))
    return np.where(top >= -bottom, 2 * high, 2 * low + 1).astype(np.uint32)


def keys(unit: np.ndarray, most: int, digits: int, tables: int) -> np.ndarray:
    """Keys (n, tables) of unit vectors, 32 bits each; equal keys of one table make a bucket."""
    out, turn = np.empty((len(unit), tables), np.uint32), rotations(unit.shape[1], digits * tables, most).astype(np.float32)
    power = np.uint32(2 * most) ** np.arange(digits, dtype=np.uint32)
    for at in range(0, len(unit), 256):
        d = _digits((unit[at : at + 256].astype(np.float32) @ turn).reshape(-1, tables, digits, most))
        out[at : at + 256] = (d * power).sum(axis=2, dtype=np.uint32)
    return out


def encode(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Signs (as 1 and -1) and correction factors of unit vectors, and the rotated vectors."""
    dim = unit.shape[1]
    turned = unit @ rotations(dim, 1, dim)
    return np.where(turned > 0, np.float32(1), np.float32(-1)), np.abs(turned).sum(axis=1) / math.sqrt(dim), turned.astype(np.float32)


def may_link(dots: np.ndarray, factor: np.ndarray, dim: int, threshold: float) -> np.ndarray:
    """Whether unbiased estimates of cosines plus their bounds reach the threshold.

    dots: products of signs with rotated vectors; factor: correction factors of the signs' vectors.
    """
    spread = np.sqrt(np.maximum(0, 1 - factor**2)) / math.sqrt(max(1, dim - 1))
    return dots / math.sqrt(dim) + SURE * spread >= threshold * factor - 1e-5


def _unit(raw, dim: int) -> np.ndarray:
    a = np.frombuffer(b"".join(raw), np.float64).reshape(-1, dim)
    a = a / np.abs(a).max(axis=1, keepdims=True)
    return a / np.linalg.norm(a, axis=1, keepdims=True)


def _bucket_pairs(group: np.ndarray, own: np.ndarray, other: np.ndarray, signs, factor, turned, threshold: float):
    """Pairs (u, v) of rows that the estimates leave open. group: bucket of each row, sorted; own: block of the row is the
    first of its bucket's two blocks; other: it is the second (both, where they are one block)."""
    first = np.flatnonzero(np.diff(group, prepend=-1))
    size, dim = np.diff(np.append(first, len(group))), signs.shape[1]
    whole = np.logical_and.reduceat(own & other, first)
    for n in np.unique(size[whole & (size > 1) & (size <= SMALL)]):
        x, y = np.triu_indices(n, 1)
        starts, step = first[whole & (size == n)], max(1, PAIRS // len(x))
        for at in range(0, len(starts), step):
            u, v = ((starts[at : at + step, None] + k).ravel() for k in (x, y))
            open_ = may_link(np.einsum("nd,nd->n", signs[u], turned[v]), factor[u], dim, threshold)
            yield u[open_], v[open_]
    for k in np.flatnonzero((size > 1) & ~(whole & (size <= SMALL))):
        rows = np.arange(first[k], first[k] + size[k])
        x, y = rows[own[rows]], rows[other[rows]]
        for at in range(0, len(x), step := max(1, 4 * PAIRS // max(1, len(y)))):
            part = x[at : at + step]
            open_ = may_link(signs[part] @ turned[y].T, factor[part, None], dim, threshold)
            if whole[k]:
                open_ &= part[:, None] < y[None, :]
            u, v = np.nonzero(open_)
            for i in range(0, len(u), PAIRS):
                yield part[u[i : i + PAIRS]], y[v[i : i + PAIRS]]


def _spanning(label: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Least label reached by the pairs (u, v) from labels that are places themselves."""
    while True:
        a, b = label[u], label[v]
        apart = a != b
        if not apart.any():
            return label
        u, v, a, b = u[apart], v[apart], a[apart], b[apart]
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while (label[label] != label).any():
            label = label[label]


def _compared(t: pd.DataFrame, threshold: float) -> pd.DataFrame:
    """Links of the buckets of one bin: (a, b, 0) spans what is linked, (a, null, w) counts links of a.

    t: (bucket, i, j, mine, no, size, dim, raw, keys), rows of one dim.
    """
    dim = int(t["dim"].iat[0])
    t = t.sort_values(["bucket", "i", "j", "no"], ignore_index=True)
    bucket, i, j, mine = (t[c].to_numpy() for c in ("bucket", "i", "j", "mine"))
    group = np.cumsum(np.append(False, (bucket[1:] != bucket[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])))
    # a vector may be in many buckets of a bin, so it is decoded once
    no, where, back = np.unique(t["no"].to_numpy(), return_index=True, return_inverse=True)
    unit, own = _unit(t["raw"].iloc[where], dim), np.frombuffer(b"".join(t["keys"].iloc[where]), np.uint32).reshape(len(no), -1)
    size, table = t["size"].to_numpy()[where], bucket >> 32
    signs, factor, turned = encode(unit)
    total, label = np.zeros(len(no), np.int64), np.arange(len(no))
    for p, q in _bucket_pairs(group, mine == i, mine == j, signs[back], factor[back], turned[back], threshold):
        u, v = back[p], back[q]
        hit = np.einsum("nd,nd->n", unit[u], unit[v]) >= threshold
        u, v, p = u[hit], v[hit], p[hit]
        first = (own[u] == own[v]).argmax(axis=1) == table[p]
        u, v = u[first], v[first]
        np.add.at(total, u, size[v])
        np.add.at(total, v, size[u])
        label = _spanning(label, u, v)
    joined, counted = np.flatnonzero(label != np.arange(len(no))), np.flatnonzero(total)
    a, b = np.append(no[joined], no[counted]), np.append(no[label[joined]], np.zeros(len(counted), np.int64))
    b = pd.array(b, "Int64")
    b[len(joined):] = pd.NA
    return pd.DataFrame({"a": a, "b": b, "w": np.append(np.zeros(len(joined), np.int64), total[counted])})


def _valid(v) -> np.ndarray | None:
    if v is None or not len(v):
        return None
    try:
        a = np.asarray(v, np.float64)
    except (TypeError, ValueError):
        return None
    return a if np.isfinite(a).all() and a.any() else None


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", threshold: float = THRESHOLD) -> DataFrame:
    id_type, spark = vectors.schema[id_col].dataType.simpleString(), vectors.sparkSession

    def digest(batches):
        for b in batches:
            a = [_valid(v) for v in b["v"]]
            raw = [None if x is None else x.tobytes() for x in a]
            yield pd.DataFrame({"id": b["id"], "cls": [None if r is None else hashlib.blake2b(r, digest_size=16).digest() for r in raw], "raw": raw})

    v = vectors.select(vectors[id_col].alias("id"), vectors[vector_col].cast("array<double>").alias("v"))
    rows = staged(v.mapInPandas(digest, f"id {id_type}, cls binary, raw binary"), "vectors")
    classes = rows.where(F.col("cls").isNotNull()).groupBy("cls").agg(F.min("id").alias("rep"), F.count("*").alias("size"), F.first("raw").alias("raw"))
    classes = classes.select(F.monotonically_increasing_id().alias("no"), "cls", "rep", "size", (F.length("raw") / 8).cast("int").alias("dim"), "raw")
    classes = staged(classes, "classes")
    plans = {r["dim"]: (r["count"], *plan(r["count"], r["dim"], threshold)) for r in classes.groupBy("dim").count().collect() if r["count"] > 1}
    least = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def code(batches):
        for b in batches:
            for dim, part in b.groupby("dim"):
                own = keys(_unit(part["raw"], dim), *plans[dim][1:])
                yield part.assign(keys=[k.tobytes() for k in own])

    coded = classes.where(F.col("dim").isin(list(plans))).select("no", "size", "dim", "raw")
    coded = staged(coded.mapInPandas(code, "no long, size long, dim int, raw binary, keys binary"), "codes")
    bins = {dim: max(least, n * tables // BIN_KEYS) for dim, (n, _, _, tables) in plans.items()}

    def deal(batches):
        held, many = {}, 0

        def flushed():
            for dim, parts in held.items():
                no, own = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
                bucket = own | np.arange(own.shape[1], dtype=np.int64) << 32
                entries = np.stack([bucket.ravel(), np.repeat(no, own.shape[1])], axis=1)
                to = (entries[:, 0].view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)) % np.uint64(bins[dim])
                order = np.argsort(to, kind="stable")
                used, begin = np.unique(to[order], return_index=True)
                parts = np.split(entries[order], begin[1:])
                yield pd.DataFrame({"dim": dim, "bin": used.astype(np.int64), "entries": [e.tobytes() for e in parts]})

        for b in batches:
            for dim, part in b.groupby("dim"):
                own = np.frombuffer(b"".join(part["keys"]), np.uint32).reshape(len(part), -1).astype(np.int64)
                held.setdefault(dim, []).append((part["no"].to_numpy(), own))
                many += own.size
            if many > HELD_KEYS:
                yield from flushed()
                held, many = {}, 0
        yield from flushed()

    def meet(t: pd.DataFrame) -> pd.DataFrame:
        e = np.frombuffer(b"".join(t["entries"]), np.int64).reshape(-1, 2)
        e = e[np.argsort(e[:, 0])]
        first = np.flatnonzero(np.diff(e[:, 0], prepend=-1))
        size = np.diff(np.append(first, len(e)))
        many = np.repeat(size, size)
        some = many > 1
        return pd.DataFrame({"bucket": e[some, 0], "no": e[some, 1], "many": many[some]})

    dealt = coded.select("no", "dim", "keys").mapInPandas(deal, "dim int, bin long, entries binary")
    members = staged(dealt.groupBy("dim", "bin").applyInPandas(meet, "bucket long, no long, many long"), "members")
    blocks = F.ceil(F.col("many") / BLOCK).cast("int")
    m = members.withColumn("mine", F.pmod(F.xxhash64("no"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    m = m.withColumn("i", F.least("mine", "other")).withColumn("j", F.greatest("mine", "other")).drop("other", "many")
    many = max(least, (members.agg(F.sum(blocks)).first()[0] or 0) // BIN_ROWS)
    m = m.join(coded, "no").withColumn("bin", F.pmod(F.xxhash64("bucket", "i", "j"), F.lit(many)))
    found = staged(m.groupBy("dim", "bin").applyInPandas(lambda t: _compared(t, threshold), "a long, b long, w long"), "links")
    counts = found.where(F.col("b").isNull()).groupBy(F.col("a").alias("no")).agg(F.sum("w").alias("others"))
    roots = components(found.where(F.col("b").isNotNull()).select("a", "b"))
    named = roots.withColumnRenamed("node", "no").join(classes.select("no", "rep"), "no")
    of = named.join(named.groupBy("root").agg(F.min("rep").alias("component")), "root").select("no", "component")
    info = classes.select("no", "cls", "rep", "size").join(counts, "no", "left").join(of, "no", "left")
    info = info.select("cls", (F.col("size") - 1 + F.coalesce("others", F.lit(0))).cast("long").alias("n_links"), F.coalesce("component", "rep").alias("component"))
    out = with_class(rows.select("id", "cls"), staged(info, "info"))
    return out.select(F.col("id").alias(id_col), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
                      F.coalesce("component", "id").alias("component_id")).withColumn("kept", F.coalesce(F.col(id_col) == F.col("component_id"), F.lit(True)))


def op3(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "embeddings"))


def oracle_sql() -> str:
    return f"""
WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
ok AS (SELECT * FROM v WHERE e IS NOT NULL AND len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
l AS (SELECT a.vec_id AS x, b.vec_id AS y FROM ok a JOIN ok b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) WHERE list_cosine_similarity(a.e, b.e) >= {THRESHOLD}),
r AS (SELECT vec_id AS x, vec_id AS y FROM v UNION SELECT r.x, l.y FROM r JOIN l ON r.y = l.x),
k AS (SELECT x, min(y) AS component_id FROM r GROUP BY x),
n AS (SELECT x, count(*) AS n FROM l GROUP BY x)
SELECT vec_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_links, component_id, vec_id = component_id AS kept
FROM v JOIN k ON k.x = vec_id LEFT JOIN n ON n.x = vec_id"""
