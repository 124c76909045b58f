import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from linkedrank.llm import packing

tokenizers = pytest.importorskip("tokenizers")
path = pytest.importorskip("public_tokenizers").path("word_bpe_49k.json")


def expand(layout):
    out = {}
    for length, first, n, seq, offset in layout.runs:
        for k in range(n):
            out.setdefault(seq + k, []).append((offset, length, first + k))
    return out


def optimum(items, capacity):
    items, best = sorted(items, reverse=True), len(items)

    def go(i, bins):
        nonlocal best
        if len(bins) >= best:
            return
        if i == len(items):
            best = len(bins)
            return
        for k in {b: j for j, b in enumerate(bins)}.values():
            if bins[k] >= items[i]:
                bins[k] -= items[i]
                go(i + 1, bins)
                bins[k] += items[i]
        go(i + 1, bins + [capacity - items[i]])

    go(0, [])
    return best


@pytest.mark.parametrize("seed", range(300))
def test_layout_is_gapless_complete_and_reduction_keeps_the_optimum(seed):
    r = random.Random(seed)
    items = [r.randint(1, 20) for _ in range(r.randint(1, 9))]
    hist = {x: items.count(x) for x in set(items)}
    seqs = expand(packing.solve(hist, 20))
    assert sorted(x for s in seqs.values() for _, x, _ in s) == sorted(items)
    for s in seqs.values():
        at = 0
        for offset, length, _ in sorted(s):
            assert offset == at
            at += length
        assert at <= 20
    left, layout = dict(hist), packing.Layout()
    packing.reduce_by_dominance(left, 20, layout)
    rest = [x for x, n in left.items() for _ in range(n)]
    assert layout.sequences + optimum(rest, 20) == optimum(items, 20)


def test_pieces_match_plain_tokenizer_and_sequences_are_full(spark, sf):
    docs = spark.read.parquet(sf() + "/documents.parquet")
    odd = spark.createDataFrame([(-1, None), (-2, ""), (-3, "x<|endoftext|>y   é It's\tÇa"), (-3, "x"), (None, "z"), (-4, "lorem ipsum " * 5000)], "doc_id long, text string")
    docs = docs.select("doc_id", "text").union(odd).withColumn("length", F.lit("clash"))
    got = packing.pack(docs, path).toPandas()
    t = tokenizers.Tokenizer.from_file(path)
    want = []
    for row in docs.collect():
        ids = t.encode(row["text"] or "", add_special_tokens=False).ids + [1]
        want += [(row["doc_id"], k, s, len(p), zlib.crc32(np.array(p, "<u4").tobytes())) for k, s in enumerate(range(0, len(ids), 4096)) for p in [ids[s : s + 4096]]]
    key = lambda r: tuple(-9.5 if x is None or x != x else x for x in r)
    assert sorted(map(key, got[["doc_id", "piece", "start", "length", "ids_crc32"]].itertuples(index=False))) == sorted(map(key, want))
    for _, s in got.sort_values("offset").groupby("sequence_id"):
        assert (s["offset"].to_numpy() == np.r_[0, s["length"].to_numpy().cumsum()[:-1]]).all() and s["length"].sum() <= 4096
    assert got["sequence_id"].nunique() <= -(-got["length"].sum() // 4096) + 2


def test_empty_table(spark):
    assert packing.pack(spark.createDataFrame([], "doc_id long, text string"), path).count() == 0


def test_encoder_equals_tokenizer_on_odd_texts():
    from hypothesis import given, settings, strategies as st

    t = tokenizers.Tokenizer.from_file(path)
    sign = st.sampled_from(list("aZéÀßÿ×ªµ²'sS!?.,0 9ſİΣς́ \t\n\r\x0b\x1c\x85<|>_☃漢") + ["<|endoftext|>", "'ll ", "It's", "'S"])

    @settings(max_examples=400, deadline=None)
    @given(st.lists(sign, max_size=14).map("".join))
    def check(text):
        e = packing.Encoder.at(path)
        at, many = e.split(pa.array([text, text]))
        ids, sizes = e.words.spelled(at)
        want = t.encode(text, add_special_tokens=False).ids
        assert ids.tolist() == 2 * want and packing.segment_sums(sizes, many).tolist() == 2 * [len(want)]

    check()


def test_merge_ranks_by_hashed_place():
    """Every merge has its rank and no other pair has one, also where pairs share a place."""
    m = packing.Encoder.at(path).merges
    keys = m.keys[:-1]
    assert (m._rank(keys // m.size, keys % m.size) == m.ranks[:-1]).all()
    place = m._place(keys)
    assert 0 < (m.hashed[place] < 0).sum() < 0.2 * len(keys)  # few pairs are still searched for
    left, right = np.random.default_rng(0).integers(0, m.size, (2, 200_000))
    known = np.isin(left * m.size + right, keys)
    assert ((m._rank(left, right) == m.NONE) == ~known).all()
