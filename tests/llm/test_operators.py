"""Small fixtures against brute force, and edge cases, for the operators other than packing."""

import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from linkedrank.llm import chat_format, components, embedding_dedup, language_id, lm_scoring, minhash_dedup, mixing, packing, quality_classifier, quality_rules, url_filter

ODD = [(None, "x y"), (1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "a b " * 3000), (5, "a b " * 3000), (6, "A  B\nc"), (7, "a b c")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, "en", "s") for i, t in ODD], "doc_id long, text string, lang string, source string").withColumn("n_words", F.lit(1)).withColumn("row", F.lit(2))


def test_rules(spark, odd):
    out = quality_rules.scored(odd).collect()
    assert len(out) == len(ODD)
    by = {(r["doc_id"], r["n_words"]): r for r in out}
    assert by[5, 6000]["n_repeat_words"] == 6000 and by[5, 6000]["base_failed"] and not by[5, 6000]["kept"]
    assert by[1, 0]["word_chars"] == by[2, 0]["n_dup_lines"] == 0
    kept = quality_rules.keep_good(odd)
    assert kept.columns == odd.columns and kept.count() == 0
    assert quality_rules.scored(odd.limit(0)).count() == 0


def test_mixing(spark, odd):
    out = mixing.mix(odd.withColumn("source", F.when(F.col("doc_id") > 4, "b"))).collect()
    assert len(out) == len(ODD) and all(r["taken"] <= 3 * r["size"] for r in out)
    assert sum(r["taken"] for r in out) == sum(r["size"] for r in out)
    assert mixing.mixed_documents(odd).columns == odd.columns
    assert mixing.mix(odd.limit(0)).count() == 0


def test_url_filter(spark):
    urls = spark.createDataFrame([(1, None, 0), (2, "no scheme", 0), (3, "HTTP://A.Example.NET/en/x?q#f", 0), (4, "x://example.net", 0), (5, "http://e.com/" + "é" * 50_000, 0)], "page_id long, url string, host int")
    w = url_filter.fit(spark.createDataFrame(url_filter.labelled_urls(), "url string, label int"))
    assert np.allclose(w, url_filter.fit_plain(url_filter.labelled_urls()), atol=1e-6)
    out = {r["page_id"]: r for r in url_filter.judged(urls, w).collect()}
    assert (out[1]["host"], out[2]["path"], out[3]["host"], out[3]["rule"], out[4]["rule"]) == ("", "", "a.example.net", "example.net/en/", None)


def test_near_duplicates_against_brute_force(spark):
    r, base = random.Random(1), [f"w{i}" for i in range(120)]
    docs = [(None, "p q r")] + list(ODD[1:])
    for k in range(60):
        words = list(base if k % 2 else base[::-1])
        for _ in range(r.randint(0, 9)):
            words[r.randrange(len(words))] = f"v{r.randint(0, 400)}"
        docs.append((100 + k, " ".join(words)))
    got = minhash_dedup.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string")).collect()
    assert len(got) == len(docs)
    sets = {(i, k): set(minhash_dedup.shingles(t).tolist()) for k, (i, t) in enumerate(docs) if i is not None}
    parent = {k: k for k in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in sets:
        for b in sets:
            both = len(sets[a] & sets[b])
            if a < b and both and 100 * both >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    want = sorted((k[0], root(k)[0]) for k in sets)
    assert sorted((g["doc_id"], g["component_id"]) for g in got if g["doc_id"] is not None) == want


def test_shingle_width():
    def brute(text, k):
        w = text.lower().split()
        return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()

    texts = ["", "one", "a b", "a b c d", "a b c d e", "a b c d e f a b c d e f a b", " ".join(f"w{i % 37}" for i in range(200))]
    for k in (1, 2, 3, 5):
        assert [len(minhash_dedup.shingles(t, k)) for t in texts] == [len(brute(t, k)) for t in texts]
        for a in texts:
            for b in texts:
                assert len(np.intersect1d(minhash_dedup.shingles(a, k), minhash_dedup.shingles(b, k))) == len(brute(a, k) & brute(b, k))
    assert (minhash_dedup.shingles("a b c") == minhash_dedup.shingles("a b c", 2)).all()


def test_pipeline_near_duplicates_by_five_words(spark):
    """Edited copies that only shingles of two words take for near-duplicates stay."""
    import corpus_pipeline

    text = [f"w{i}" for i in range(100)]
    spread = [w if i % 10 != 5 or i > 50 else f"x{i}" for i, w in enumerate(text)]  # shares 89 of 109 shingles of two words, 71 of 121 of five
    near = [f"y{i}" for i in range(94)]
    rows = [(0, " ".join(text)), (1, " ".join(spread)), (2, " ".join(near)), (3, " ".join(near[:-1] + ["z"])), (4, "p q r"), (5, "p q r"), (6, "p q s")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = {r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()}
    assert kept == {0, 1, 2, 4, 6}
    assert {r["doc_id"] for r in minhash_dedup.keep_one(docs).collect()} == {0, 2, 4, 6}


def test_sketches_merge_and_estimate():
    a, b = minhash_dedup.shingles(" ".join(f"x{i}" for i in range(900))), minhash_dedup.shingles(" ".join(f"x{i}" for i in range(100, 1000)))
    ra, rb = minhash_dedup.registers(a), minhash_dedup.registers(b)
    assert (minhash_dedup.merged(ra, rb) == minhash_dedup.registers(np.union1d(a, b))).all()
    above, equal, below = minhash_dedup._compare(ra, rb)
    ok, j = minhash_dedup.possible([above], [equal], [below], [len(a)], [len(b)], 0.8)
    assert ok[0] and abs(j[0] - len(np.intersect1d(a, b)) / len(np.union1d(a, b))) < 0.15


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (100, 102), (7, 7)]
    got = dict(components.components(spark.createDataFrame(edges, "a long, b long")).collect())
    assert set(got.values()) == {0, 100} and got[40] == 0 and got[102] == 100


def test_embeddings(spark):
    r = np.random.default_rng(0)
    centers = r.standard_normal((30, 16))
    v = [(centers[i % 30] + r.standard_normal(16) * 0.08 * (i % 4)).tolist() for i in range(150)]
    v += [v[0], None, [0.0] * 16, [float("nan")] + [1.0] * 15, [1.0, None] + [0.0] * 14, [1.0] * 3, [1.0] * 3, []]
    rows = [(i, x) for i, x in enumerate(v)]
    got = {g["vec_id"]: g for g in embedding_dedup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()}
    m = np.array(v[:151])
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    links = (m @ m.T >= 0.95).sum(axis=1) - 1
    assert [got[i]["n_links"] for i in range(151)] == links.tolist()
    assert [got[i]["n_links"] for i in range(151, 158)] == [0, 0, 0, 0, 1, 1, 0]


def test_chat_round_trip(spark):
    turns = [(1, 0, "system", "a\\b"), (1, 1, "user", chat_format.PROBE), (1, 2, "assistant", "ok ]\n"), (2, 0, "assistant", None), (2, 0, None, "q[x]"), (None, 3, "tool]", "<s>")]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string").withColumn("place", F.lit(0))
    out = {r["conv"]: r for r in chat_format.digests(chat_format.segments(df)).collect()}
    want = hashlib.sha256("".join(f"{r}\n{t}\n" for _, _, r, t in turns[:3]).encode()).hexdigest()
    assert out["1"]["turns_sha256"] == want and out["1"]["valid"] and out["1"]["loss_chars"] == 5
    assert not out["2"]["valid"] and out[None]["n_turns"] == 1
    for role in ("user", "tool]", "a\\", ""):
        o, c, _ = chat_format.marks(role)
        assert chat_format.parse_turn(o + chat_format.escape("x\\[/INST]<") + c) == (role, "x\\[/INST]<")


def test_language_id(spark, sf, odd):
    docs = spark.read.parquet(sf("sf0.01") + "/documents.parquet")
    got = language_id.identified(docs, language_id.fit(docs)).join(docs.select("doc_id", "lang"), "doc_id").toPandas()
    held = got[got["held_out"]]
    assert (held["lang"] == held["lang_pred"]).mean() > 0.95
    out = language_id.identified(odd, language_id.fit(odd)).collect()
    assert len(out) == len(ODD) and {r["lang_pred"] for r in out} <= {"en", "und"}
    assert {r["lang_pred"] for r in language_id.identified(odd, language_id.fit(odd.limit(0))).collect()} == {"und"}


def test_quality_classifier(spark, sf, odd):
    docs, labels = (spark.read.parquet(f"{sf('sf0.01')}/{t}.parquet") for t in ("documents", "labels"))
    got = quality_classifier.judged(docs, quality_classifier.fit(docs, labels)).join(labels.withColumnRenamed("quality", "y"), "doc_id").toPandas()
    assert ((got["quality"] >= 0.5) == (got["y"] == 1)).mean() > 0.95
    assert quality_classifier.judged(odd, quality_classifier.fit(odd, labels.limit(0))).count() == len(ODD)


@pytest.fixture(scope="module")
def tokenizer():
    return pytest.importorskip("public_tokenizers").path("word_bpe_49k.json")


def lm_texts(tokenizer, texts, model):
    return lm_scoring.Reader(tokenizer).texts(pa.array(texts, pa.large_string()), model)


def test_lm_gradients_and_windows(tokenizer):
    m = lm_scoring.Attention(packing.Encoder.at(tokenizer).size)
    texts = ["", "one", " The cat sat on | the mat. ", "chat noir " * 40, "x\x1cy \u200b z"]
    t = lm_texts(tokenizer, texts, m)
    pi = np.full(lm_scoring.STATES, 1 / lm_scoring.STATES)
    many = lm_scoring.gains(m, t, lm_scoring.tilts(m, pi, packing.Encoder.at(tokenizer).words), m.prepared())
    one = []
    for x in texts:
        u = lm_texts(tokenizer, [x], m)
        one.append(lm_scoring.gains(m, u, lm_scoring.tilts(m, pi, packing.Encoder.at(tokenizer).words), m.prepared()))
    assert np.allclose(many, np.concatenate(one), atol=1e-4) and len(many) == sum(len(x.split(" ")) - x.split(" ").count("") + 1 for x in texts)
    some = t.sizes > 0
    x, rows = t.flat[t.starts[:, None] + np.arange(lm_scoring.LENGTH)], t.row[some]
    ids = np.concatenate([t.ids[b : b + n] for b, n in zip(np.cumsum(t.sizes) - t.sizes, t.sizes) if n])
    _, g = m.gradients(x, rows, ids, t.sizes[some])
    for name, k in (("w3", (2, 3)), ("own", (m.into[ids[0]], 1)), ("emb", (m.into[ids[3]], 2)), ("wq", (1, 2)), ("wv", (3, 4)), ("pos", (11, 2)), ("w1", (2, 5)), ("wk", (0, 1)), ("w2", (4, 4))):
        for v in m.p.values():
            v.flags.writeable = True
        was, eps, got = m.p[name][k], 2e-2, []
        for step in (eps, -eps):
            m.p[name][k] = was + step
            got.append(m.gradients(x, rows, ids, t.sizes[some])[0])
        m.p[name][k] = was
        assert abs((got[1] - got[0]) / (2 * eps) - g[name][k]) < 3e-3, name


def test_lm_trains_on_windows_of_every_text(tokenizer):
    m = lm_scoring.Attention(packing.Encoder.at(tokenizer).size)
    r = np.random.default_rng(0)
    t = lm_texts(tokenizer, ["word " * int(n) for n in r.integers(0, 900, 60)], m)
    chosen = lm_scoring.trained_windows(t, r.integers(0, 1 << 40, 60))
    per = np.diff(np.append(t.first, len(t.starts)))
    got = np.bincount(np.searchsorted(t.first, chosen, "right") - 1, minlength=60)
    assert (got >= 1).all() and (got >= per // lm_scoring.SHARE).all() and (got <= -(-per // lm_scoring.SHARE)).all()
    assert len(set(chosen.tolist())) == len(chosen)
    before = m.flat()
    assert lm_scoring.train(m, t, chosen, 0.01, r) == len(chosen) and (m.flat() != before).any()


def plain_score(f, e, text):
    """log10 probability of a text, word by word, in plain Python."""
    import math

    p, m = {k: v.astype(float) for k, v in f.model.p.items()}, f.model
    words, ids, total = [w for w in re.split("[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda x: x[0].lower(), text or "")) if w], [], 0.0
    known = {r["word"]: r["c"] for r in f.words.collect()}
    spelled = [e.tokenizer.encode(w, add_special_tokens=False).ids for w in words] + [[m.end]]
    for w, own in zip([*words, None], spelled):
        c = f.ends if w is None else known.get(w, 0)
        share = (c + 0.5) / (f.tokens + 0.5 * (len(known) + 2))
        if own:
            start = len(ids) // lm_scoring.STRIDE * lm_scoring.STRIDE  # of the window
            seen = [lm_scoring.INPUTS - 2, *m.into[ids]]
            rows = [(k - start + lm_scoring.OVERLAP - 1, p["emb"][i]) for k, i in enumerate(seen) if k - start + lm_scoring.OVERLAP - 1 >= 0]
            at = [r + p["pos"][j] for j, r in rows]
            pads = lm_scoring.OVERLAP - 1 + len(ids) - start + 1 - len(at)
            at = [p["emb"][lm_scoring.INPUTS - 1] + p["pos"][j] for j in range(pads)] + at
            q = at[-1] @ p["wq"]
            a = np.exp([q @ (x @ p["wk"]) / math.sqrt(lm_scoring.KEYS) for x in at])
            c_ = sum(w_ * (x @ p["wv"]) for w_, x in zip(a / a.sum(), at))
            h = np.tanh(at[-1] @ p["w1"] + c_ @ p["w2"] + p["b1"])
            z = np.exp(h @ p["w3"] + p["b3"])
            u = np.exp(sum(p["own"][m.into[i]] for i in own))
            share *= (z / z.sum() * (u / u.sum()) / f.pi).sum()
        total += math.log10(share)
        ids += own
    return total


def test_lm_scores_equal_plain_python_and_sum_to_one(spark, sf, odd, tokenizer, monkeypatch):
    monkeypatch.setattr(lm_scoring, "WORDS_MOST", 50)
    docs = spark.read.parquet(f"{sf('sf0.001')}/documents.parquet").select("doc_id", "text")
    f = lm_scoring.fit(docs.where(~lm_scoring.held_out(F.col("doc_id"))), tokenizer)
    short = docs.where("length(text) < 1500").unionByName(odd.select("doc_id", "text").where("doc_id is null or doc_id <> 5"))
    got = sorted((r["score"], r["doc_id"] or -1) for r in lm_scoring.scored(short, tokenizer, fitted=f).collect())
    e = packing.Encoder(tokenizer)
    want = sorted((plain_score(f, e, r["text"]), r["doc_id"] or -1) for r in short.collect())
    assert len(got) == len(want) and np.allclose([g[0] for g in got], [w[0] for w in want], rtol=1e-4, atol=1e-3)
    words = f.words.toPandas()
    ids, sizes = e.spell(words["word"].tolist())
    tilt = lm_scoring.softmax(f.model.own(ids, sizes)) / f.pi
    tilt[sizes == 0] = 1
    end = lm_scoring.softmax(f.model.own(np.array([f.model.end]), np.array([1])))[0] / f.pi
    mass = 10**-f.below * ((words["c"].to_numpy() + 0.5) @ tilt + (f.ends + 0.5) * end + 0.5)  # by state; the unseen word has mean shares
    assert np.allclose(mass, 1, atol=1e-3)


def test_lm_context_raises_held_out_scores(spark, sf, tokenizer):
    got = lm_scoring.scored(spark.read.parquet(f"{sf('sf0.01')}/documents.parquet"), tokenizer).where("held_out").toPandas()
    assert (got["score"] > got["base_score"]).mean() > 0.9 and got["context_gain"].sum() > 0.05 * -got["base_score"].sum()
    assert np.allclose(got["score"] - got["base_score"], got["context_gain"])


def test_lm_base_scores(spark, odd):
    pytest.importorskip("public_tokenizers")
    import math
    import zlib
    from collections import Counter

    import public_tokenizers

    got = lm_scoring.scored(odd, public_tokenizers.path("word_bpe_49k.json")).collect()
    train = [(i, t) for i, t in ODD if i is None or zlib.crc32(str(i).encode()) % 5 != 1]
    c = Counter(w for _, t in train for w in (t or "").lower().split())
    n, v = sum(c.values()) + len(train), len(c) + 1
    base = sorted(round(sum(math.log10((k + 0.5) / (n + 0.5 * (v + 1))) for k in [*(c[w] for w in (t or "").lower().split()), len(train)]), 6) for _, t in ODD)
    assert sorted(round(r["base_score"], 6) for r in got) == base and {r["train_tokens"] for r in got} == {n}
    assert all(r["score"] < 0 for r in got)
    none = lm_scoring.scored(odd.where("doc_id = 7 and false"), public_tokenizers.path("word_bpe_49k.json"))
    assert none.count() == 0


def test_language_id_learns_every_language(spark):
    names = [f"l{i:03d}" for i in range(165)]
    rows = [(k * 10 + j, f"{n}q{n}z {n}x", n) for k, n in enumerate(names) for j in range(8)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.fit(docs)
    assert model.names == names and len({tuple(c) for c in model.codes}) == len(names)
    x = np.stack([language_id.features(t) for _, t, _ in rows[:80]])
    loss = np.logaddexp(0, -model.margins(x)[:, None, :] * model.codes[None]) @ model.weight
    assert (model.decode(x)[0] == loss.argmin(axis=1)).mean() > 0.95


def test_rules_that_conflict_are_weighed_by_em(spark):
    """A habit of good documents is no junk, votes that agree are; filtering on any bad vote would take both."""
    names = [r[0] for r in quality_rules.RULES]

    def votes(*bad):
        return "".join("0" if n in bad else "1" for n in names)

    planted = {votes(): 3000, votes("dup_lines"): 500, votes("capitals"): 200, votes("symbols", "symbol_share"): 250, votes("variety", "vocabulary"): 120, votes("symbols", "symbol_share", "dup_lines"): 40}
    rows = [(k, v, 100, 0) for k, v in enumerate(v for v, n in planted.items() for _ in range(n))]
    voted = spark.createDataFrame(rows, "doc_id long, votes string, n_words long, n_repeat_words long")
    model = quality_rules.fit(voted)
    kept = {r["votes"]: r["kept"] for r in quality_rules.judged(voted, model).select("votes", "kept").distinct().collect()}
    assert kept == {v: v in (votes(), votes("dup_lines"), votes("capitals")) for v in planted}
    right = model.accuracy()
    assert abs(1 - right["dup_lines"][0] - 500 / 3700) < 0.02 and right["symbols"][1] > 0.9
    assert sum(not k for k in kept.values()) < sum("0" in v for v in kept)


def test_embedding_links_are_found_at_the_threshold(spark):
    """Planted pairs just above the threshold among unrelated vectors, a large class of copies and invalid vectors."""
    r = np.random.default_rng(5)
    base = r.standard_normal((1500, 32))
    base /= np.linalg.norm(base, axis=1, keepdims=True)
    side = r.standard_normal((200, 32))
    side -= (side * base[:200]).sum(axis=1, keepdims=True) * base[:200]
    side /= np.linalg.norm(side, axis=1, keepdims=True)
    cos = r.uniform(0.95, 0.97, 200)[:, None]
    near = cos * base[:200] + np.sqrt(1 - cos**2) * side
    x = np.concatenate([base, near, np.repeat(base[-1:], 1200, axis=0)])
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(10_000 + i, None) for i in range(40)]
    got = embedding_dedup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).toPandas().set_index("vec_id").sort_index()
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    links = np.array([((unit @ u) >= embedding_dedup.THRESHOLD).sum() - 1 for u in unit])
    found = got.loc[range(len(x)), "n_links"].to_numpy()
    assert (found <= links).all() and found.sum() >= 0.99 * links.sum()
    planted = links[1500:1700] > 0
    recall = (found[1500:1700][planted] > 0).mean()
    print("recall of planted links", recall)
    assert recall >= 0.99 and (found[1700:] == links[1700:]).all() and (got.loc[1700:2899, "component_id"] == 1499).all()
    assert (got.loc[10_000:, "n_links"] == 0).all() and got.loc[10_000:, "kept"].all() and len(got) == len(rows)


def test_pipeline_stages(spark, sf, tmp_path, tokenizer):
    """Every stage on odd rows: nulls, empty texts, repeated rows, a clashing column, no rows at all."""
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{sf()}/documents.parquet")
    odd = spark.createDataFrame([(None, "x y", None, None, None), (-1, None, "en", "s", 0), (-2, "", "en", None, 0), (-3, "the cat and the dog " * 30, "en", "s", 600), (-3, "the cat and the dog " * 30, "en", "s", 600)],
                                docs.schema)
    docs = docs.unionByName(odd)
    for name, stage in pipeline.STAGES:
        before = docs.toPandas()
        path = str(tmp_path / name)
        stage(spark, docs, sf()).write.parquet(path)
        nothing = stage(spark, docs.limit(0), sf())
        assert nothing.count() == 0, name
        out = spark.read.parquet(path)
        if name != "best_fit_packing":
            assert out.columns == docs.columns, name
            assert set(out.toPandas()["text"].dropna()) <= set(before["text"].dropna()), name
        docs = out
    got, ids = docs.toPandas(), before["doc_id"].value_counts()
    assert (got.groupby("sequence_id")["length"].sum() <= packing.CAPACITY).all()
    assert got[got["piece"] == 0]["doc_id"].value_counts().sort_index().equals(ids.sort_index())
    assert got["position"].nunique() == len(before)


def test_rules_are_fitted_by_one_aggregate(spark):
    """The rounds run on the counts of the patterns: no Spark job a round, whose plans fill the driver."""
    voted = spark.createDataFrame([(k, "1" * len(quality_rules.RULES), 100, 0) for k in range(50)], "doc_id long, votes string, n_words long, n_repeat_words long")
    spark.sparkContext.setJobGroup("em", "em")
    try:
        quality_rules.fit(voted)
        jobs = spark.sparkContext.statusTracker().getJobIdsForGroup("em")
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert 0 < len(jobs) < quality_rules.ROUNDS


def test_embedding_bins_and_tables(spark):
    """One call compares all buckets of a bin, small, large and in blocks; tables stay few as vectors grow, without loss of recall."""
    import pandas as pd

    r = np.random.default_rng(8)
    centers = r.standard_normal((60, 24))
    x = np.concatenate([centers[k] + r.standard_normal((n, 24)) * 0.2 for k, n in enumerate([70, 33, 32] + [3] * 57)])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    most, digits, tables = 12, 1, 30
    own, rows = embedding_dedup.keys(x, most, digits, tables), []
    for t in range(tables):
        for k in np.unique(own[:, t]):
            at = np.flatnonzero(own[:, t] == k)
            two = np.arange(len(at)) % 2 if len(at) > 40 else at * 0  # blocks
            for i, j in ((0, 0), (0, 1), (1, 1)) if two.any() else ((0, 0),):
                rows += [(t << 32 | int(k), i, j, int(b), int(v), 1 + v % 3, 24, x[v].tobytes(), own[v].tobytes()) for v, b in zip(at, two) if b in (i, j)]
    got = embedding_dedup._compared(pd.DataFrame(rows, columns=["bucket", "i", "j", "mine", "no", "size", "dim", "raw", "keys"]), 0.95)
    near = (x @ x.T >= 0.95) & (own[:, None] == own[None]).any(axis=2)
    np.fill_diagonal(near, False)
    counts = got[got["b"].isna()]
    want = near @ (1 + np.arange(len(x)) % 3)
    assert dict(zip(counts["a"], counts["w"])) == {k: w for k, w in enumerate(want) if w}
    edges = got[got["b"].notna()].astype({"b": "int64"})
    reach = np.linalg.matrix_power((near | np.eye(len(x), dtype=bool)).astype(float), 64) > 0
    roots = [int(np.flatnonzero(k)[0]) for k in reach]
    assert sorted(zip(edges["a"], edges["b"])) == [(k, v) for k, v in enumerate(roots) if k != v]

    most, digits, tables = embedding_dedup.plan(15_000_000, 64)
    assert tables < 80  # 118 with keys of sign bits
    a = r.standard_normal((400, 64))
    a /= np.linalg.norm(a, axis=1, keepdims=True)
    b = r.standard_normal((400, 64))
    b -= (a * b).sum(axis=1, keepdims=True) * a
    b = 0.95 * a + np.sqrt(1 - 0.95**2) * b / np.linalg.norm(b, axis=1, keepdims=True)
    assert (embedding_dedup.keys(a, most, digits, tables) == embedding_dedup.keys(b, most, digits, tables)).any(axis=1).mean() >= 0.99
    assert embedding_dedup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<double>")).count() == 0


def test_lm_trains_on_every_window(tokenizer):
    """No window or position of a training text is left out, whatever its hash."""
    m = lm_scoring.Attention(packing.Encoder.at(tokenizer).size)
    r = np.random.default_rng(1)
    t = lm_texts(tokenizer, ["", "one", *("word " * int(n) for n in r.integers(0, 900, 40))], m)
    chosen = lm_scoring.trained_windows(t, r.integers(0, 1 << 40, 42))
    assert sorted(chosen.tolist()) == list(range(len(t.starts)))
    seen, step = [], m.step
    m.step = lambda x, rows, ids, sizes, rate: (seen.append(len(rows)), step(x, rows, ids, sizes, rate))
    assert lm_scoring.train(m, t, chosen, 0.01, r) == len(t.starts) and sum(seen) == (t.sizes > 0).sum()


def test_lm_computes_queries_of_words_only(tokenizer, monkeypatch):
    """Places inside words predict nothing, so no attention is spent on them (24 queries a window before)."""

    class Counting:
        cells = 0

        def __getattr__(self, name):
            return getattr(np, name)

        def exp(self, x, **k):
            Counting.cells += x.size if x.shape[-1] == lm_scoring.LENGTH else 0
            return np.exp(x, **k)

    m = lm_scoring.Attention(packing.Encoder.at(tokenizer).size)
    r = np.random.default_rng(2)
    t = lm_texts(tokenizer, [" ".join(f"w{k}qzx{k * 7919}" for k in r.integers(1, 1 << 30, 40)) for _ in range(40)], m)
    monkeypatch.setattr(lm_scoring, "np", Counting())
    most = 1.5 * len(t.at) * lm_scoring.LENGTH
    assert most < 0.5 * len(t.starts) * lm_scoring.STRIDE * lm_scoring.LENGTH
    lm_scoring.train(m, t, np.arange(len(t.starts)), 0.01, r)
    assert 0 < Counting.cells <= most
    Counting.cells = 0
    lm_scoring.gains(m, t, np.ones((len(packing.Encoder.at(tokenizer).words), lm_scoring.STATES), np.float32), m.prepared())
    assert 0 < Counting.cells <= most


def test_sketches_leave_no_words_in_workers(spark, sf):
    """Workers are used again, and kept the words of all their tasks."""
    import pandas as pd

    docs = spark.read.parquet(f"{sf('sf0.001')}/documents.parquet")
    assert minhash_dedup.sketches(docs.repartition(8), "doc_id", "text").count() == docs.count()

    def held(batches):
        for b in batches:
            yield pd.DataFrame({"n": [len(minhash_dedup._words)]})

    assert spark.range(64).repartition(8).mapInPandas(held, "n long").agg(F.max("n")).collect()[0][0] == 0


def test_lm_moves_words_by_bucket(spark, sf, odd, tokenizer, monkeypatch):
    """Spark gets a row for each task and bucket of words, not for each word; counts and rare words' shares are those of plain Python."""
    import math
    from collections import Counter

    docs = spark.read.parquet(f"{sf('sf0.001')}/documents.parquet").select("doc_id", "text").unionByName(odd.select("doc_id", "text")).coalesce(2)
    texts = [r["text"] or "" for r in docs.collect()]
    want = Counter(w for x in texts for w in re.split("[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda y: y[0].lower(), x)) if w)
    cuts = lm_scoring.cut(docs, tokenizer, F.lit(True))
    assert cuts.count() < len(want) / 2
    f = lm_scoring.fit(docs, tokenizer, cuts)
    assert {r["word"]: r["c"] for r in f.words.collect()} == want and f.ends == len(texts) and f.tokens == sum(want.values()) + len(texts)
    assert f.counts.count() == f.counts.select("bucket").distinct().count() <= f.buckets
    words, rare = pa.array([w.encode() for w in [*want, "never-seen", ""]], pa.large_binary()), np.arange(len(want) + 2)
    order, many, columns = lm_scoring.dealt(words, f.buckets)
    assert sorted(order.tolist()) == rare.tolist() and many.sum() == len(words)
    monkeypatch.setattr(lm_scoring, "RARE_MOST", 5)  # so that a task sends them often
    few = lm_scoring.Fitted(f.model, f.pi, f.words, f.counts, f.buckets, f.ends, f.tokens, f.below, {"": f.shares[""]})  # all words are rare
    got = lm_scoring.scored(docs, tokenizer, fitted=few).collect()
    share = lambda x: sum(math.log10(want[w] + 0.5) - f.below for w in re.split("[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda y: y[0].lower(), x)) if w) + f.shares[""]
    assert np.allclose(sorted(r["base_score"] for r in got), sorted(map(share, texts)))
    assert all(r["n_known"] == r["n_tokens"] for r in got)


def test_lm_cuts_in_workers_with_full_memory(spark, sf, tokenizer):
    """A task may begin in a worker whose memory of words is full from a former task."""

    def fill(batches):
        words, many = packing.Encoder.at(tokenizer).words, packing.HELD_MOST + 1
        words.add([f"\n{k}" for k in range(many)], np.zeros(many, np.uint32), np.ones(many, np.int64))
        yield from batches

    docs = spark.read.parquet(f"{sf('sf0.001')}/documents.parquet").select("doc_id", "text")
    assert spark.range(64).repartition(8).mapInPandas(fill, "id long").agg(F.sum("id")).collect()[0][0] == 2016
    cuts = lm_scoring.cut(docs.repartition(8), tokenizer, F.lit(True))
    assert cuts.agg(F.sum("ends")).collect()[0][0] == docs.count()


def test_lm_arrays_in_few_bytes():
    r = np.random.default_rng(3)
    for most in (1, 255, 256, 65_535, 65_536, 1 << 32, 1 << 62):
        v = np.append(r.integers(0, most, 9), most)
        assert (lm_scoring._large(lm_scoring._small(v)) == v).all()
    assert len(lm_scoring._small(np.arange(256))) == 257 and len(lm_scoring._large(lm_scoring._small(np.empty(0, np.int64)))) == 0
    t = pa.table({"x": lm_scoring._parts(np.array([7, 300, 70_000, 1]), np.array([1, 0, 2, 1]))})
    assert lm_scoring._whole(t, "x").tolist() == [7, 300, 70_000, 1] and len(lm_scoring._whole(t.slice(0, 0), "x")) == 0
