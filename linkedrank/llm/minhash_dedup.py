"""Operator 6: near-duplicates by SetSketch registers.

A document is the set of its distinct shingles of ``width`` words (2 in op6), kept as 64-bit hashes (a set of a
million shingles holds two with one hash with a probability under 1e-7). Its sketch holds M
registers: the minimum of an exponential variable per register over the set, truncated to
exponentially spaced steps of base B. Registers of a union are the maxima, so sketches merge; equal registers
get likelier with similarity, so bands of registers find candidates; counts of larger, equal
and smaller registers give the joint likelihood of the similarity, which drops hopeless
candidates; what remains is confirmed on full sets.

Equal sets are one class (hot groups of copies never meet again after one partial aggregate).
In each band bucket, classes are first tested against the bucket's least class only, which is
linear in the bucket. Buckets whose classes are then still in several components go on, in
blocks of bounded size: first each class with its likeliest partner of another component
(again linear), then every remaining pair between components that the registers cannot rule
out, compared on full sets within the block, which emits only links that join components. So
no link that matters is lost within the candidates, and no group ever emits its pairs.

Edge cases: null or empty texts and texts of blanks only have an empty set and link with
nothing; a text of fewer words than the width is a set of one; repeated rows share a class; rows without id are their
own component (null); an empty table gives an empty result; extra columns are ignored.
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

WIDTH = 2  # words of a shingle in op6
M, ROWS, BASE, RATE = 100, 5, 1.02, 20.0
Q = 2**16 - 2
BLOCK = 1024
BROADCAST_MOST = 500_000
DOUBT = 12.0  # log likelihood by which 0.8 must lose before a pair is ruled out
WORDS_MOST = 1_000_000
_rng = np.random.default_rng(20240607)
_MUL = (_rng.integers(0, 2**32, M, dtype=np.uint64) | 1).astype(np.uint32)
_ADD = _rng.integers(0, 2**32, M, dtype=np.uint64).astype(np.uint32)
_K1, _K2, _K3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


class _Words(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        h = self[word] = xxhash.xxh64_intdigest(word)
        return h


_words = _Words()


def _forgetting(run):
    """``run`` over a task's batches; then the worker, which later tasks and stages use again, gives the words' memory back."""

    def task(batches):
        try:
            yield from run(batches)
        finally:
            forget()

    return task


def forget() -> None:
    _words.clear()  # named here, as a nested function would be sent with a copy


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _K2
    x = (x ^ (x >> np.uint64(27))) * _K3
    return x ^ (x >> np.uint64(31))


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """Sorted distinct hashes of a whole text's shingles of ``width`` words."""
    if not text:
        return np.empty(0, np.uint64)
    words = text.encode("utf-8", "replace").lower().split()
    if len(_words) > WORDS_MOST:
        _words.clear()
    h = np.fromiter(map(_words.__getitem__, words), np.uint64, len(words))
    if not len(h):
        return h
    many = max(1, len(h) - width + 1)
    rolled = h[:many].copy()
    for k in range(1, min(width, len(h))):
        rolled = rolled * _K1 + h[k : k + many]
    if len(h) < width:
        return _mix(rolled ^ _K1)
    return np.unique(_mix(rolled))


def registers(hashes: np.ndarray) -> np.ndarray:
    """SetSketch registers of a set of hashes (0s for the empty set)."""
    if not len(hashes):
        return np.zeros(M, np.uint16)
    low, least = (hashes >> np.uint64(32)).astype(np.uint32), np.full(M, 2**32 - 1, np.uint32)
    for at in range(0, len(low), 2048):
        np.minimum(least, (low[at : at + 2048, None] * _MUL + _ADD).min(axis=0), out=least)
    x = -np.log1p(-(least + 0.5) / 2**32) / RATE
    return np.clip(np.floor(1 - np.log(x) / math.log(BASE)), 0, Q + 1).astype(np.uint16)


def merged(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Registers of the union of two sets."""
    return np.maximum(a, b)


def _step(x):
    return -np.log1p(-x * (BASE - 1) / BASE) / math.log(BASE)


_GRID = np.linspace(0.0, 1.0, 51)


def possible(above, equal, below, n_a, n_b, at_least: float) -> tuple[np.ndarray, np.ndarray]:
    """Whether the joint likelihood leaves a similarity of ``at_least`` open, and its best estimate.

    above/equal/below: registers of a larger than, equal to, smaller than those of b.
    """
    above, equal, below = (np.asarray(x, np.float64)[:, None] for x in (above, equal, below))
    n_a, n_b = np.asarray(n_a, np.float64), np.asarray(n_b, np.float64)
    u, v = n_a / (n_a + n_b), n_b / (n_a + n_b)
    top = np.minimum(u / v, v / u)

    def likelihood(j):
        p = _step(np.maximum(u[:, None] - v[:, None] * j, 0))
        q = _step(np.maximum(v[:, None] - u[:, None] * j, 0))
        tiny = 1e-12
        return above * np.log(p + tiny) + below * np.log(q + tiny) + equal * np.log(np.maximum(1 - p - q, tiny))

    grid = likelihood(_GRID[None, :] * top[:, None])
    best = grid.argmax(axis=1)
    j = _GRID[best] * top
    wanted = likelihood(np.minimum(at_least, top)[:, None])[:, 0]
    return (top >= at_least - 1e-9) & ((j >= at_least) | (grid.max(axis=1) - wanted <= DOUBT)), j


def _compare(a: np.ndarray, b: np.ndarray):
    return (a > b).sum(axis=-1), (a == b).sum(axis=-1), (a < b).sum(axis=-1)


def sketches(docs: DataFrame, id_col: str, text_col: str, width: int = WIDTH) -> DataFrame:
    """(id, n, cls, regs, bands): set size, 128-bit digest of the set, registers, band keys."""
    id_type = docs.schema[id_col].dataType.simpleString()
    weights = _mix(np.arange(1, ROWS + 1, dtype=np.uint64) * _K1)

    def run(batches):
        for b in batches:
            ns, cls, regs, bands = [], [], [], []
            for text in b["text"]:
                s = shingles(text, width)
                r = registers(s)
                ns.append(len(s))
                cls.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                regs.append(r.tobytes())
                mixed = (r.reshape(-1, ROWS).astype(np.uint64) + np.uint64(1)) * weights
                key = _mix(mixed.sum(axis=1, dtype=np.uint64) + np.arange(M // ROWS, dtype=np.uint64) * _K3)
                bands.append(key.view(np.int64))
            yield pd.DataFrame({"id": b["id"], "n": ns, "cls": cls, "regs": regs, "bands": bands})

    d = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text"))
    return d.mapInPandas(_forgetting(run), f"id {id_type}, n long, cls binary, regs binary, bands array<long>")


def _sets(docs: DataFrame, id_col: str, text_col: str, wanted: DataFrame, width: int = WIDTH) -> DataFrame:
    """(cls, hashes) of the wanted classes: (id, cls)."""
    ids = wanted.select("id").distinct()
    if ids.count() <= BROADCAST_MOST:
        ids = F.broadcast(ids)
    d = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text")).join(ids, "id", "left_semi")

    def run(batches):
        for b in batches:
            sets = [shingles(t, width) for t in b["text"]]
            yield pd.DataFrame({"id": b["id"], "cls": [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], "hashes": [s.view(np.int64) for s in sets]})

    id_type = docs.schema[id_col].dataType.simpleString()
    return d.mapInPandas(_forgetting(run), f"id {id_type}, cls binary, hashes array<long>").join(wanted, ["id", "cls"], "left_semi").drop("id").dropDuplicates(["cls"])


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose full sets reach the similarity."""
    sa = sets.select(F.col("cls").alias("a"), F.col("hashes").alias("ha"))
    sb = sets.select(F.col("cls").alias("b"), F.col("hashes").alias("hb"))
    both = F.size(F.array_intersect("ha", "hb"))
    return (
        pairs.join(sa, "a").join(sb, "b").withColumn("both", both)
        .where(100 * F.col("both") >= percent * (F.size("ha") + F.size("hb") - F.col("both"))).select("a", "b")
    )


def _likely(pairs: DataFrame, classes: DataFrame, at_least: float) -> DataFrame:
    """Pairs that the likelihood does not rule out."""
    ca = classes.select(F.col("cls").alias("a"), F.col("n").alias("na"), F.col("regs").alias("ra"))
    cb = classes.select(F.col("cls").alias("b"), F.col("n").alias("nb"), F.col("regs").alias("rb"))
    near = (F.least("na", "nb") >= F.greatest("na", "nb") * (at_least - 1e-9))

    def run(batches):
        for t in batches:
            if len(t):
                ra, rb = (np.frombuffer(b"".join(t[c]), np.uint16).reshape(-1, M) for c in ("ra", "rb"))
                ok, _ = possible(*_compare(ra, rb), t["na"], t["nb"], at_least)
                yield t.loc[ok, ["a", "b"]]

    return pairs.join(ca, "a").join(cb, "b").where(near).mapInPandas(run, "a binary, b binary")


def _blocks(members: DataFrame) -> DataFrame:
    """Deal the rows of each bucket (key, size, cls, ...) to pairs of blocks i <= j."""
    blocks = F.ceil(F.col("size") / BLOCK).cast("int")
    m = members.withColumn("mine", F.pmod(F.xxhash64("cls"), blocks).cast("int"))
    m = m.withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    return m.withColumn("i", F.least("mine", "other")).withColumn("j", F.greatest("mine", "other")).drop("other", "size")


class _Pair:
    """Two blocks of one bucket: registers, sizes and component labels of x against y."""

    def __init__(self, t: pd.DataFrame, at_least: float):
        t = t.sort_values("cls", ignore_index=True)
        self.same, self.at_least = t["i"].iat[0] == t["j"].iat[0], at_least
        self.label = pd.factorize(t["root"])[0]
        self.n, self.cls, self.t = t["n"].to_numpy(), t["cls"].to_numpy(), t
        self.regs = np.frombuffer(b"".join(t["regs"]), np.uint16).reshape(-1, M)
        self.x = np.flatnonzero(t["mine"] == t["i"].iat[0])
        self.y = np.flatnonzero(t["mine"] == t["j"].iat[0])
        # equal registers are at least as likely as the similarity; 5.5 deviations below it is hopeless
        self.fewest = M * at_least - 5.5 * math.sqrt(M * at_least * (1 - at_least))

    def open(self, k: int, after: bool) -> np.ndarray:
        """Places of y in another component that the registers do not rule out for place k."""
        at = self.y[self.y > k] if self.same and after else self.y
        n = self.n[at]
        at = at[(self.label[at] != self.label[k]) & (np.minimum(n, self.n[k]) >= np.maximum(n, self.n[k]) * (self.at_least - 1e-9))]
        return at[(self.regs[at] == self.regs[k]).sum(axis=1) >= self.fewest] if len(at) else at


def _likeliest(members: DataFrame, at_least: float) -> DataFrame:
    """Each class with its likeliest partner of another component, per bucket and block."""

    def run(t: pd.DataFrame) -> pd.DataFrame:
        p, out = _Pair(t, at_least), {}
        for k in p.x:
            at = p.open(k, after=False)
            if len(at):
                ok, est = possible(*_compare(p.regs[k], p.regs[at]), np.full(len(at), p.n[k]), p.n[at], at_least)
                if ok.any():
                    q = at[ok][est[ok].argmax()]
                    out[min(p.cls[k], p.cls[q]), max(p.cls[k], p.cls[q])] = None
        return pd.DataFrame(list(out), columns=["a", "b"])

    return _blocks(members).groupBy("key", "i", "j").applyInPandas(run, "a binary, b binary").distinct()


def _joining_links(members: DataFrame, percent: int) -> DataFrame:
    """Links on full sets between different components, per bucket and block; of the links of a
    block, those that join what the block has not joined yet. members also hold bands, hashes."""

    def run(t: pd.DataFrame) -> pd.DataFrame:
        p, out = _Pair(t, percent / 100), []
        key, bands = p.t["key"].iat[0], np.stack(p.t["bands"])
        sets = list(p.t["hashes"])
        ids = np.unique(np.concatenate(sets), return_inverse=True)[1]
        ids = np.split(ids, np.cumsum([len(x) for x in sets])[:-1])
        mark = np.zeros(max(map(np.max, ids)) + 1, bool)
        for k in p.x:
            at = p.open(k, after=True)
            if len(at):
                first = (bands[at] == bands[k]).argmax(axis=1)  # a pair is compared in one of its buckets
                at = at[bands[k][first] == key]
                mark[ids[k]] = True
                for q in at:
                    if p.label[q] != p.label[k]:
                        both = int(mark[ids[q]].sum())
                        if 100 * both >= percent * (len(ids[k]) + len(ids[q]) - both):
                            out.append((p.cls[k], p.cls[q]))
                            p.label[p.label == p.label[q]] = p.label[k]
                mark[ids[k]] = False
        return pd.DataFrame(out, columns=["a", "b"])

    return _blocks(members).groupBy("key", "i", "j").applyInPandas(run, "a binary, b binary")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = 80, width: int = WIDTH) -> DataFrame:
    """One row per document: id, n_shingles, component_id (least id reachable), kept."""
    at_least = percent / 100
    all_docs = staged(sketches(docs, id_col, text_col, width), "sketches")
    full = all_docs.where((F.col("n") > 0) & F.col("id").isNotNull())
    reps = full.groupBy("cls").agg(F.min("id").alias("id"))
    classes = staged(full.join(reps, ["cls", "id"]).dropDuplicates(["cls"]).select("cls", "id", "n", "regs", "bands"), "classes")
    entries = classes.select("cls", F.explode("bands").alias("key"))
    buckets = staged(entries.groupBy("key").agg(F.min("cls").alias("lead"), F.count("*").alias("size")).where("size > 1"), "buckets")
    members = staged(entries.join(buckets, "key"), "members")
    wanted = staged(classes.join(members.select("cls").distinct(), "cls", "left_semi"), "wanted")
    star = members.where("cls <> lead").select(F.col("lead").alias("a"), F.col("cls").alias("b")).distinct()
    tested = staged(_likely(star, wanted, at_least), "tested")
    sets = staged(_sets(docs, id_col, text_col, wanted.select("id", "cls"), width), "sets")
    links = staged(_verified(tested, sets, percent), "links")
    roots = components(links)
    for last in (False, True):
        m = members.join(roots.withColumnRenamed("node", "cls"), "cls", "left").withColumn("root", F.coalesce("root", "cls"))
        mixed = staged(m.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("key"), "mixed")
        if mixed.isEmpty():
            break
        m = m.join(mixed, "key", "left_semi").drop("lead")
        if last:
            found = _joining_links(m.join(wanted.select("cls", "n", "regs", "bands"), "cls").join(sets, "cls"), percent)
        else:
            more = _likeliest(m.join(wanted.select("cls", "n", "regs"), "cls"), at_least).join(tested, ["a", "b"], "left_anti")
            found = _verified(staged(more, "tested"), sets, percent)
        found = staged(found, "links")
        if not found.isEmpty():
            links = links.union(found)
            roots = components(links)
    ids = classes.select("cls", F.col("id").alias("rep"))
    named = roots.join(ids.withColumnRenamed("cls", "node"), "node")
    least = named.groupBy("root").agg(F.min("rep").alias("component_id"))
    of = named.join(least, "root").select(F.col("node").alias("cls"), "component_id")
    of = ids.join(of, "cls", "left").select("cls", F.coalesce("component_id", "rep").alias("component_id"))
    lonely = (F.col("n") == 0) | F.col("id").isNull()
    out = with_class(all_docs.select("id", F.col("n").alias("n_shingles"), F.when(~lonely, F.col("cls")).alias("cls"), lonely.alias("lonely")), staged(of, "of"))
    return out.select(F.col("id").alias(id_col), "n_shingles", F.when(F.col("lonely"), F.col("id")).otherwise(F.col("component_id")).alias("component_id")).withColumn(
        "kept", F.coalesce(F.col(id_col) == F.col("component_id"), F.lit(True)))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH) -> DataFrame:
    """The rows of ``docs`` with one document per group; of rows with one id, one stays."""
    found = staged(near_duplicates(docs, id_col, text_col, width=width), "groups")
    ids = found.where(F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max("kept").alias("kept"), F.count("*").alias("many"))
    ids = staged(ids.where(~F.col("kept") | (F.col("many") > 1)), "decided")
    gone, many = ids.where(~F.col("kept")).select("id"), ids.where("kept").select("id")

    def small(t):
        return F.broadcast(t) if t.count() <= BROADCAST_MOST else t

    left = docs.join(small(gone), docs[id_col] == F.col("id"), "left_anti")
    if many.isEmpty():
        return left
    many = small(many)
    again = left.join(many, left[id_col] == F.col("id"), "left_semi").dropDuplicates([id_col])
    return left.join(many, left[id_col] == F.col("id"), "left_anti").unionByName(again)


def op6(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents"))


def oracle_sql() -> str:
    up, low = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return f"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), '{up}', '{low}'), '[ \\t\\n\\x0B\\f\\r]+'), lambda x: x <> '') AS ws FROM documents),
s AS (SELECT doc_id, CASE WHEN len(ws) = 1 THEN ws WHEN len(ws) = 0 THEN [] ELSE list_distinct(list_transform(generate_series(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1])) END AS sh FROM w),
n AS (SELECT doc_id, len(sh) AS n FROM s),
e AS (SELECT doc_id, unnest(sh) AS x FROM s),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS inter FROM e a JOIN e b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM c JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * inter >= 80 * (na.n + nb.n - inter)),
g AS (SELECT a AS x, b AS y FROM l UNION ALL SELECT b, a FROM l),
r AS (SELECT doc_id AS x, doc_id AS y FROM n UNION SELECT r.x, g.y FROM r JOIN g ON r.y = g.x),
k AS (SELECT x, min(y) AS component_id FROM r GROUP BY x)
SELECT doc_id, CAST(n AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM n JOIN k ON k.x = doc_id"""
