"""Operator 9: scoring by a causal self-attention model on subword ids.

The model reads the subword ids before a word and predicts the word. One attention layer with
learned positions and a tanh layer give, at each position, shares ``g`` of STATES hidden states; a word
has shares ``r`` of the same states by its own ids; the corpus has mean shares ``pi``. A word's
probability is its smoothed corpus share times sum(g * r / pi). Since pi is the mean of r under the corpus
shares, the probabilities of all training words and of one unseen word of mean shares sum to one
after any context. (As in the baseline, each unseen word gets the mass of that one; its own ids
then decide its states.) The gain over the corpus share is thus what the context tells.

What is gathered: word counts over every training document, pi over every distinct word, and the weights
by numpy gradient steps on all windows of every training document, each once (SHARE = 1; a larger SHARE would train on
each SHARE-th of a document, at a place given by a hash). START_STEPS steps on START_DOCS documents in one
task give all tasks the same start, then ROUNDS passes over disjoint parts of the training documents
follow; each task goes on from the common weights over its windows, and the weights of
the tasks are averaged by their windows. Steps and counts thus grow with the rows. Subword ids share
INPUTS rows of weights by a fixed hash.

Long texts are cut into windows that overlap by the context of their first position; every
word, and the end, is scored once. Windows of many texts form one batch, and the causal mask is the same for all.

Every text is cut and its words are spelled once (``cut``): records of RECORD_WORDS words or one longer text
hold the numbers of their words in a dictionary of their own, with its spellings, and training and scoring
read those. Words are dealt into buckets by a hash of their bytes, and the words that a task has for one bucket are
one row, so that Spark moves rows by task and bucket, not by word; each bucket's counts are summed on their own. Words with a
high count (at most WORDS_MOST of them, picked by powers of two) are looked up in the workers; the other words
of the texts go to their buckets and the answers back to their texts, so no vocabulary is ever held whole.

Edge cases: a null or empty text is the end alone; repeated rows are scored alike and count as often
as they occur; without training documents contexts tell nothing and score equals base_score; a word
that the tokenizer gives no ids keeps its corpus share; texts of any length work; null ids are
scored and not held out; extra columns are ignored.
"""

from __future__ import annotations

import copy
import math
from dataclasses import dataclass
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkedrank.llm import packing
from linkedrank.llm.packing import Encoder, Spellings, groups, segment_sums, text_column
from linkedrank.sources import read_table, staged

STRIDE, OVERLAP = 24, 12
LENGTH = STRIDE + OVERLAP - 1
WIDTH, KEYS, HIDDEN, STATES, INPUTS = 16, 8, 16, 16, 4096
SHARE, ROUNDS, START_DOCS, START_STEPS = 1, 2, 400, 150
START_BYTES = 8_000_000
BATCH, CHUNK, START_RATE, ROUND_RATE = 256, 512, 0.02, 0.01
WORDS_MOST, AVERAGERS = 300_000, 8
FIRST_IDS, PARTS = 6, 6  # ids of a word that are summed in turn, the others by runs; parts of a batch by words of a window
RECORD_WORDS, GROUP_WORDS, CUT_BYTES = 150_000, 400_000, 8_000_000  # of a record of spelled texts; of records that are read at a time; of texts that are cut at a time
BUCKETS, RARE_MOST = 512, 500_000  # of words, at least (else one for each shuffle partition); rare words that a task sends to them at a time
END = None  # stands among words for the end of a text


def softmax(z: np.ndarray) -> np.ndarray:
    if z.size and not (z.min() > -60 and z.max() < 60):  # else exponents are safe as they are
        z = z - z.max(axis=-1, keepdims=True)
    z = np.exp(z)
    z /= (z @ np.ones(z.shape[-1], z.dtype))[..., None]
    return z


class Attention:
    """Weights of the model, its gradients and its Adam steps."""

    NAMES = ("emb", "pos", "wq", "wk", "wv", "w1", "w2", "b1", "w3", "b3", "own")
    SMALL = NAMES[1:-1]  # these take their steps as one

    def __init__(self, size: int, seed: int = 3):
        r, shape = np.random.default_rng(seed), {
            "emb": (INPUTS, WIDTH), "pos": (LENGTH, WIDTH), "wq": (WIDTH, KEYS), "wk": (WIDTH, KEYS), "wv": (WIDTH, WIDTH), "w1": (WIDTH, HIDDEN),
            "w2": (WIDTH, HIDDEN), "b1": (HIDDEN,), "w3": (HIDDEN, STATES), "b3": (STATES,), "own": (INPUTS, STATES)}
        scale = {"emb": 0.5, "own": 0.5, "pos": 0.3, "b1": 0.0, "b3": 0.0}
        self.p = {k: (r.standard_normal(s) * scale.get(k, 1 / math.sqrt(s[0]))).astype(np.float32) for k, s in shape.items()}
        # rows of ids; the end, what precedes a text and what follows it have rows of their own
        self.end = size
        self.into = np.append(np.arange(size) * 2654435761 % 4294967296 * (INPUTS - 3) >> 32, INPUTS - 3)
        at = np.arange(OVERLAP - 1, LENGTH)
        self.seen = (np.arange(LENGTH)[None, :] <= at[:, None]).astype(np.float32)
        self.restart()

    def restart(self) -> None:
        """Forget the moments of the steps."""
        self.t, sizes = 0, {"emb": self.p["emb"].shape, "own": self.p["own"].shape, "small": sum(self.p[k].size for k in self.SMALL)}
        self.moments = {k: (np.zeros(n, np.float32), np.zeros(n, np.float32)) for k, n in sizes.items()}

    def flat(self) -> np.ndarray:
        return np.concatenate([self.p[k].ravel() for k in self.NAMES])

    def load(self, flat: np.ndarray) -> None:
        at = 0
        for k in self.NAMES:
            n = self.p[k].size
            self.p[k] = flat[at : at + n].reshape(self.p[k].shape).astype(np.float32)
            at += n
        self.restart()

    def windows(self, ids: np.ndarray, many: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(input rows of all windows end to end, start of each window in them, first window of each text).

        ids: all texts in one row, ends included; many: ids of each text. Query t of a text's windows sees the ids before id t.
        """
        per = -(-many // STRIDE)
        base, first = np.cumsum(per * STRIDE + OVERLAP) - per * STRIDE - OVERLAP, np.cumsum(per) - per
        flat = np.full(int((per * STRIDE + OVERLAP).sum()) + 1, INPUTS - 1, np.int64)
        flat[base + OVERLAP - 1] = INPUTS - 2
        flat[np.repeat(base + OVERLAP - np.cumsum(many) + many, many) + np.arange(len(ids))] = self.into[ids]
        return flat, np.repeat(base - first * STRIDE, per) + STRIDE * np.arange(int(per.sum())), first

    def own(self, ids: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Logits of the states of words, from their ids."""
        order, at = np.argsort(-sizes, kind="stable"), self.into.take(ids)
        begin, out = (np.cumsum(sizes) - sizes).take(order), np.zeros((len(sizes), STATES), np.float32)
        left = len(sizes) - np.cumsum(np.bincount(np.minimum(sizes, FIRST_IDS), minlength=FIRST_IDS + 1))  # words of more than so many ids
        for nth, n in enumerate(left[:FIRST_IDS].tolist()):  # the nth ids of all words at once, as few words have many
            out[:n] += self.p["own"].take(at.take(begin[:n] + nth), axis=0)
        n = int(np.count_nonzero(sizes > FIRST_IDS))
        if n:
            more = sizes.take(order[:n]) - FIRST_IDS
            stops = np.cumsum(more)
            rest = at.take(np.repeat(begin[:n] + FIRST_IDS - stops + more, more) + np.arange(stops[-1]))
            out[:n] += np.add.reduceat(self.p["own"].take(rest, axis=0), stops - more)
        back = np.empty(len(order), np.int64)
        back[order] = np.arange(len(order))
        return out.take(back, axis=0)

    def prepared(self) -> dict:
        """Products of embeddings and positions with the weights, and whether exponents may overflow.

        Values carry a last column of ones, so that the sum of the attention comes with the values'.
        """
        p, ones = self.p, lambda v, fill: np.concatenate([v, np.full((len(v), 1), fill, np.float32)], axis=1)
        wk, wv, last = p["wk"] / np.float32(math.sqrt(KEYS)), p["wv"] @ p["w2"], p["pos"][OVERLAP - 1 :]
        out = {"k": p["emb"] @ wk, "k_at": p["pos"] @ wk, "v": ones(p["emb"] @ wv, 1), "v_at": ones(p["pos"] @ wv, 0), "q": p["emb"] @ p["wq"],
               "q_at": last @ p["wq"], "h": p["emb"] @ p["w1"], "h_at": last @ p["w1"] + p["b1"]}
        keys, queries = (np.linalg.norm(np.abs(out[m]).max(axis=0) + np.abs(out[m + "_at"]).max(axis=0)) for m in "kq")
        return out | {"clip": keys * queries > 60, "clip_z": (np.abs(p["w3"]).sum(axis=0) + np.abs(p["b3"])).max() > 60}

    def masses(self, x: np.ndarray, rows: np.ndarray, w: dict) -> np.ndarray:
        """Shares of the states, up to a factor, at the queries ``rows`` (window times STRIDE plus place) of windows x; w: ``prepared()``."""
        order, place, key, slot, at, seen, parts = padded(rows, len(x))
        x = x.take(order, axis=0)
        k, v, late = w["k"].take(x, axis=0), w["v"].take(x, axis=0), x.ravel().take(key)
        k += w["k_at"]
        v += w["v_at"]
        q = w["q"].take(x.ravel().take(at), axis=0)
        q += w["q_at"].take(seen, axis=0)
        a, c = np.empty((len(at), LENGTH), np.float32), np.empty((len(at), HIDDEN + 1), np.float32)
        for i, s, shape in parts:
            np.matmul(q[s].reshape(shape), k[i].transpose(0, 2, 1), out=a[s].reshape(shape))
        if w["clip"]:
            np.clip(a, -60, 60, out=a)
        np.exp(a, out=a)
        a *= self.seen.take(seen, axis=0)  # the causal mask
        for i, s, shape in parts:
            np.matmul(a[s].reshape(shape), v[i], out=c[s].reshape(shape))
        c = c.take(slot, axis=0)
        h = c[:, :HIDDEN] / c[:, HIDDEN:]
        h += w["h"].take(late, axis=0)
        h += w["h_at"].take(place, axis=0)
        np.tanh(h, out=h)
        z = h @ self.p["w3"]
        z += self.p["b3"]
        if w["clip_z"]:
            np.clip(z, -60, 60, out=z)
        return np.exp(z, out=z)

    def step(self, x: np.ndarray, rows: np.ndarray, ids: np.ndarray, sizes: np.ndarray, rate: float) -> float:
        """One Adam step on the words that queries ``rows`` of windows x predict; returns their mean gain.

        ids, sizes: ids of those words. The mean shares are those of the batch, and take part in the gradient.
        """
        gain, g = self.gradients(x, rows, ids, sizes)
        self.t += 1
        far = math.sqrt(1 - 0.99**self.t)  # moments are kept as plain sums, without the factors 0.1 and 0.01
        pace, least = rate / (1 - 0.9**self.t) * far, 1e-7 * far
        for k, (m, s) in self.moments.items():
            v = np.concatenate([g[name].ravel() for name in self.SMALL]) if k == "small" else g[k]
            m *= 0.9
            m += v
            s *= 0.99
            u = v * v
            s += u
            np.sqrt(s, out=u)
            u += least
            np.divide(m, u, out=u)
            u *= pace
            if k == "small":
                at = 0
                for name in self.SMALL:
                    w = self.p[name]
                    w -= u[at : at + w.size].reshape(w.shape)
                    at += w.size
            else:
                self.p[k] -= u
        return gain

    def gradients(self, x, rows, ids, sizes) -> tuple[float, dict]:
        p, many, n, scale = self.p, len(x), np.float32(len(rows)), np.float32(1 / math.sqrt(KEYS))
        order, _, key, slot, at, seen, parts = padded(rows, many)
        slots = len(at)
        x = x.take(order, axis=0)
        e = p["emb"].take(x, axis=0)
        e += p["pos"]
        e = e.reshape(-1, WIDTH)  # products with weights are taken of all windows at once
        eq = e.take(at, axis=0)
        q, both = eq @ (p["wq"] * scale), np.concatenate([p["wk"], p["wv"]], axis=1)
        kv = e @ np.concatenate([both, np.zeros((WIDTH, 1), np.float32)], axis=1)
        kv[:, -1] = 1  # the column of ones gives the attention's sums
        kv = kv.reshape(many, LENGTH, -1)
        k, v = kv[:, :, :KEYS], kv[:, :, KEYS:]
        a, c = np.empty((slots, LENGTH), np.float32), np.empty((slots, WIDTH + 1), np.float32)
        for w, s, shape in parts:
            np.matmul(q[s].reshape(shape), k[w].transpose(0, 2, 1), out=a[s].reshape(shape))
        if a.max() > 60 or a.min() < -60:
            np.clip(a, -60, 60, out=a)
        np.exp(a, out=a)
        a *= self.seen.take(seen, axis=0)
        for w, s, shape in parts:
            np.matmul(a[s].reshape(shape), v[w], out=c[s].reshape(shape))
        c = c.take(slot, axis=0)
        total, late = c[:, WIDTH:], eq.take(slot, axis=0)
        value = c[:, :WIDTH] / total
        h = late @ p["w1"]
        h += value @ p["w2"]
        h += p["b1"]
        np.tanh(h, out=h)
        g, r = softmax(h @ p["w3"] + p["b3"]), softmax(self.own(ids, sizes))
        ones, states = np.ones(len(rows), np.float32), np.ones(STATES, np.float32)
        pi = ones @ r / n
        post = g * r
        post /= pi
        gain = (post @ states)[:, None]
        post /= gain
        dz, pull = g - post, ones @ post / n / pi
        dz /= n
        du = r * (1 + pull - (r @ pull)[:, None])
        du -= post
        du /= n
        dh = h * h
        np.subtract(1, dh, out=dh)
        dh *= dz @ p["w3"].T
        out = {"w3": h.T @ dz, "b3": ones @ dz, "w1": late.T @ dh, "w2": value.T @ dh, "b1": ones @ dh}
        # the last column takes the mean of the values' pull off, as the shares of an attention sum to one
        dc, back = np.zeros((slots, WIDTH + 1), np.float32), np.empty((len(rows), WIDTH + 1), np.float32)
        np.divide(dh @ p["w2"].T, total, out=back[:, :WIDTH])
        back[:, WIDTH] = -np.einsum("ij,ij->i", back[:, :WIDTH], value)
        dc[slot] = back
        ds, dq = np.empty_like(a), np.empty_like(q)
        back = np.empty((many, LENGTH, KEYS + WIDTH), np.float32)
        back[: parts[0][0].start] = 0  # windows of no query
        dk, dv = back[:, :, :KEYS], back[:, :, KEYS:]
        for w, s, shape in parts:
            np.matmul(a[s].reshape(shape).transpose(0, 2, 1), dc[s].reshape(shape)[:, :, :WIDTH], out=dv[w])
            np.matmul(dc[s].reshape(shape), v[w].transpose(0, 2, 1), out=ds[s].reshape(shape))
        ds *= a
        for w, s, shape in parts:
            np.matmul(ds[s].reshape(shape), k[w], out=dq[s].reshape(shape))
            np.matmul(ds[s].reshape(shape).transpose(0, 2, 1), q[s].reshape(shape), out=dk[w])  # q is scaled
        dq *= scale
        back = back.reshape(-1, KEYS + WIDTH)
        into, de = e.T @ back, back @ both.T
        out |= {"wq": eq.T @ dq, "wk": into[:, :KEYS], "wv": into[:, KEYS:]}
        late = dq.take(slot, axis=0) @ p["wq"].T
        late += dh @ p["w1"].T
        de[key] += late
        out["pos"] = (np.ones(many, np.float32) @ de.reshape(many, -1)).reshape(LENGTH, WIDTH)
        out["emb"], out["own"] = _spread(x.ravel(), de), _spread(self.into.take(ids), du.take(np.repeat(np.arange(len(sizes)), sizes), axis=0))
        return float(np.log(gain).mean()), out


def padded(rows: np.ndarray, many: int) -> tuple:
    """The layout in which only the queries ``rows``, ascending, of ``many`` windows are computed.

    Windows are ordered by their number of queries, cut into PARTS and padded to one width in each. Returns that order; of each
    query its place in the window, its position among those of all ordered windows, and its slot; of each slot its position and
    place (0 where padded); and of each part its windows, its slots and the shape of these.
    """
    window = rows // STRIDE
    place = rows - window * STRIDE
    count = np.bincount(window, minlength=many)
    order, to = np.argsort(count, kind="stable"), np.empty(many, np.int64)
    to[order] = np.arange(many)
    bounds = [many * i // PARTS for i in range(PARTS + 1)]
    widths = [int(count[order[hi - 1]]) if hi > lo else 0 for lo, hi in zip(bounds, bounds[1:])]
    wide = np.repeat(widths, np.diff(bounds))
    slot = ((np.cumsum(wide) - wide)[to] - np.cumsum(count) + count)[window] + np.arange(len(rows))
    key = to[window] * LENGTH + place + OVERLAP - 1
    at, seen = np.zeros(int(wide.sum()), np.int64), np.zeros(int(wide.sum()), np.int64)
    at[slot], seen[slot] = key, place
    stops = np.cumsum([0, *(w * (hi - lo) for w, lo, hi in zip(widths, bounds, bounds[1:]))]).tolist()
    parts = [(slice(lo, hi), slice(i, j), (hi - lo, w, -1)) for lo, hi, i, j, w in zip(bounds, bounds[1:], stops, stops[1:], widths) if i < j]
    return order, place, key, slot, at, seen, parts


def _spread(at: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Sums of the rows of v by their row ``at`` of the weights."""
    pairs = v.shape[1] // 2  # two columns are added at once, as the parts of a complex number
    out = np.zeros(INPUTS * pairs, np.complex64)
    np.add.at(out, np.arange(INPUTS * pairs).reshape(INPUTS, pairs).take(at, axis=0).ravel(), np.ascontiguousarray(v).view(np.complex64).ravel())
    return out.view(np.float32).reshape(INPUTS, -1)


@dataclass
class Texts:
    """Words of texts by number, ends included, and the query that predicts each."""

    ids: np.ndarray
    sizes: np.ndarray  # ids of each word
    at: np.ndarray  # number of each word
    many: np.ndarray  # words of each text
    flat: np.ndarray
    starts: np.ndarray
    first: np.ndarray  # first window of each text
    row: np.ndarray  # query of each word, by window times STRIDE plus place


def placed(model: Attention, spellings: Spellings, at: np.ndarray, many: np.ndarray) -> Texts:
    """Texts of the words numbered ``at``, ``many`` of each text, with their windows."""
    ids, sizes = spellings.spelled(at)
    lengths = segment_sums(sizes, many)
    flat, starts, first = model.windows(ids, lengths)
    row = np.cumsum(sizes) - sizes + np.repeat(first * STRIDE - np.cumsum(lengths) + lengths, many)
    return Texts(ids, sizes, at, many, flat, starts, first, row)


class Reader:
    """Cuts batches of texts into numbered words; the encoder remembers the words."""

    def __init__(self, tokenizer: str):
        self.encoder = Encoder.at(tokenizer)

    def _number(self, word: str, ids: list[int]) -> int:
        words = self.encoder.words
        if word not in words.number:
            words.add([word], np.array(ids, np.uint32), np.array([len(ids)]))
        return words.number[word]

    def full(self) -> bool:
        """Whether the next texts start the memory anew."""
        return len(self.encoder.words) > packing.HELD_MOST

    def numbers(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the words of all texts in one row, an end after each text, and the words of each."""
        at, many = self.encoder.split(pc.ascii_lower(texts))
        blank = self.encoder.words.number.get("")  # around texts that start or end with white space
        if blank is not None:
            keep = at != blank
            many = segment_sums(keep.astype(np.int64), many)
            at = at[keep]
        return np.insert(at, np.cumsum(many), self._number(END, [self.encoder.size])), many + 1

    def texts(self, texts: pa.Array, model: Attention) -> Texts:
        at, many = self.numbers(texts)
        return placed(model, self.encoder.words, at, many)


def trained_windows(t: Texts, hashes: np.ndarray) -> np.ndarray:
    """Numbers of the windows that are trained on: of each text each SHARE-th from a hashed place on, and one at least."""
    per = np.diff(np.append(t.first, len(t.starts)))
    text = np.repeat(np.arange(len(per)), per)
    nth = np.arange(len(t.starts)) - t.first[text]
    return np.flatnonzero(nth % SHARE == (hashes % np.minimum(SHARE, per))[text])


def train(model: Attention, t: Texts, chosen: np.ndarray, rate: float, r: np.random.Generator, steps: int | None = None) -> int:
    """Adam steps on batches of the chosen windows in random order, each once (steps: so many random batches instead)."""
    words = np.flatnonzero(t.sizes > 0)
    bounds = np.searchsorted(t.row[words] // STRIDE, np.arange(len(t.starts) + 1))
    begin = np.cumsum(t.sizes) - t.sizes
    order, done = r.permutation(chosen), 0
    parts = (r.choice(chosen, BATCH) for _ in range(steps)) if steps else (order[i : i + BATCH] for i in range(0, len(order), BATCH))
    for nth, part in enumerate(parts):
        count = bounds[part + 1] - bounds[part]
        if not count.sum():
            continue
        w = words.take(np.repeat(bounds[part] - np.cumsum(count) + count, count) + np.arange(int(count.sum())))
        rows = t.row.take(w) + np.repeat((np.arange(len(part)) - part) * STRIDE, count)
        sizes = t.sizes.take(w)
        stops = np.cumsum(sizes)
        ids = t.ids.take(np.repeat(begin.take(w) - stops + sizes, sizes) + np.arange(stops[-1]))
        fading = 1 - 0.9 * nth / steps if steps else len(part) / BATCH
        model.step(t.flat.take(t.starts[part][:, None] + np.arange(LENGTH)), rows, ids, sizes, rate * min(1.0, (model.t + 1) / 30) * fading)
        done += len(part)
    return done


def gains(model: Attention, t: Texts, tilt: np.ndarray, w: dict) -> np.ndarray:
    """log10 of sum(g * r / pi) of each word, in one row. tilt: r / pi by number of word."""
    out = np.empty(len(t.at), np.float64)
    bounds = np.searchsorted(t.row // STRIDE, np.arange(0, len(t.starts) + CHUNK, CHUNK))
    for i, (lo, hi) in enumerate(zip(bounds[:-1], bounds[1:])):
        first = i * CHUNK
        x = t.flat.take(t.starts[first : first + CHUNK][:, None] + np.arange(LENGTH))
        g = model.masses(x, t.row[lo:hi] - first * STRIDE, w)
        out[lo:hi] = np.einsum("ij,ij->i", g, tilt.take(t.at[lo:hi], axis=0)) / (g @ np.ones(STATES, np.float32))
    return np.log10(out)


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 1, F.lit(False))


def warm_start(docs: DataFrame, tokenizer: str) -> Attention:
    """A model trained for START_STEPS steps in one task on the documents of the least hashes."""
    ids = staged(docs.select("doc_id").where(F.col("doc_id").isNotNull()).orderBy(F.xxhash64("doc_id"), "doc_id").limit(START_DOCS).distinct(), "lm-sample")
    sample = docs.join(F.broadcast(ids), "doc_id", "left_semi").limit(2 * START_DOCS).select("text").repartition(1)

    def run(batches):
        reader, taken, size = Reader(tokenizer), [], 0
        for texts in (text_column(b, "text") for b in batches):
            first, last = next(groups(texts, START_BYTES - size)) if size < START_BYTES else (0, 0)
            taken.append(texts.slice(first, last - first))
            size += pc.sum(pc.binary_length(taken[-1])).as_py() or 0
        if not taken:
            return
        model = Attention(reader.encoder.size)
        t = reader.texts(pa.concat_arrays(taken), model)
        train(model, t, np.arange(len(t.starts)), START_RATE, np.random.default_rng(4), START_STEPS)
        yield pa.RecordBatch.from_arrays([pa.array([model.flat().astype("<f4").tobytes()], pa.binary())], names=["weights"])

    model = Attention(Encoder.at(tokenizer).size)
    got = sample.mapInArrow(run, "weights binary").collect()
    if got:
        model.load(np.frombuffer(got[0]["weights"], "<f4"))
    return model


def _small(values: np.ndarray) -> bytes:
    """Values of at least 0 in as few bytes each as hold the largest; the last byte tells how many."""
    size = next(n for n in (1, 2, 4, 8) if not len(values) or not int(values.max()) >> 8 * n)
    return values.astype(f"<u{size}").tobytes() + bytes([size])


def _large(value) -> np.ndarray:
    size = memoryview(value)[-1]
    return np.frombuffer(value, f"<u{size}", (len(value) - 1) // size)


def _parts(values: np.ndarray, sizes: np.ndarray, write=_small) -> pa.Array:
    """Binaries of consecutive runs of ``values``."""
    stops = np.cumsum(sizes).tolist()
    return pa.array([write(values[i:j]) for i, j in zip([0, *stops], stops)], pa.binary())


def _whole(table: pa.Table, name: str) -> np.ndarray:
    """Values of all binaries of a column in one row."""
    return np.concatenate([np.empty(0, np.uint8), *map(_large, table.column(name).to_pylist())])


def _joined(column: pa.Array, first: int, last: int) -> list[np.ndarray]:
    return [_large(column[k].as_buffer()) for k in range(first, last)]


_FACTORS = np.random.default_rng(5).integers(0, 1 << 63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _flat(words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all words end to end, and the bytes of each. words: of a large type."""
    if not len(words):
        return np.empty(0, np.uint8), np.empty(0, np.int64)
    stops = np.frombuffer(words.buffers()[1], np.int64)[words.offset : words.offset + len(words) + 1]
    return np.frombuffer(words.buffers()[2] or b"", np.uint8)[stops[0] : stops[-1]], np.diff(stops)


def _words(table: pa.Table) -> pa.Array:
    """Words of all rows, from ``keys`` and ``key_sizes``."""
    sizes = _whole(table, "key_sizes").astype(np.int64)
    stops = np.concatenate([[0], np.cumsum(sizes)])
    return pa.Array.from_buffers(pa.large_binary(), len(sizes), [None, pa.py_buffer(stops), pa.py_buffer(b"".join(table.column("keys").to_pylist()))])


def dealt(words: pa.Array, buckets: int) -> tuple[np.ndarray, np.ndarray, dict]:
    """The order of words (of a large type) by bucket, the words of each bucket that has some, and the columns of these buckets."""
    flat, sizes = _flat(words)
    place = np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    h = segment_sums((flat + np.uint64(1)) * _FACTORS.take(place & 63), sizes)
    h ^= h >> np.uint64(32)
    h *= _FACTORS[0]
    bucket = ((h >> np.uint64(33)) % np.uint64(buckets)).astype(np.int32)
    order = np.argsort(bucket, kind="stable")
    many = np.bincount(bucket, minlength=1)
    some = np.flatnonzero(many)
    many = many[some]
    flat, sizes = _flat(words.take(pa.array(order)))
    return order, many, {"bucket": pa.array(some, pa.int32()), "keys": _parts(flat, segment_sums(sizes, many), np.ndarray.tobytes), "key_sizes": _parts(sizes, many)}


COUNTS = "bucket int, keys binary, key_sizes binary, c binary, id_sizes binary, key_ids binary"


def buckets_of(df: DataFrame) -> int:
    return max(BUCKETS, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def cut(docs: DataFrame, tokenizer: str, training: Column) -> DataFrame:
    """Staged spelled texts. docs: (doc_id, text). Three kinds of rows:

    (bucket, keys, key_sizes, c, id_sizes, key_ids): words of a bucket, their bytes end to end and the bytes of each, the times that
    a task met them in training texts, and their ids; (ends): texts of training that it met;
    (part, ...): a record of texts, of training round ``part`` or, with part = ROUNDS, of no training. Its words
    are joined by blanks, which no word holds; the empty word is the end.
    """
    hashed = docs.select("doc_id", "text", F.xxhash64("doc_id", F.length("text")).alias("hash")).select(
        "*", F.when(training, F.pmod("hash", F.lit(ROUNDS))).otherwise(ROUNDS).cast("int").alias("part"))
    id_type = docs.schema["doc_id"].dataType.simpleString()
    schema = f"{COUNTS}, ends long, part int, doc array<{id_type}>, hash binary, many binary, at binary, sizes binary, ids binary, words binary"
    buckets = buckets_of(docs)

    def run(batches):
        reader, counts, names, named = Reader(tokenizer), np.zeros(0, np.int64), [], None

        def rows(n, **columns):
            return pa.RecordBatch.from_arrays([columns.get(k, pa.nulls(n, t)) for k, t in types.items()], names=list(types))

        def counted():
            words = reader.encoder.words
            end = words.number[END]
            yield rows(1, ends=pa.array(counts[end : end + 1]))
            counts[end] = 0
            some = np.flatnonzero(counts)
            order, many, columns = dealt(pa.array(map(names.__getitem__, some.tolist()), pa.large_string()), buckets)
            ids, sizes = words.spelled(some[order])
            yield rows(len(many), **columns, c=_parts(counts[some[order]], many), id_sizes=_parts(sizes, many), key_ids=_parts(ids, segment_sums(sizes, many)))

        types = None
        for b in batches:
            types = types or {"bucket": pa.int32(), **dict.fromkeys(("keys", "key_sizes", "c", "id_sizes", "key_ids"), pa.binary()), "ends": pa.int64(), "part": pa.int32(),
                              "doc": pa.list_(b.schema.field("doc_id").type), **dict.fromkeys(("hash", "many", "at", "sizes", "ids", "words"), pa.binary())}
            texts, parts = text_column(b, "text"), b.column("part").to_numpy()
            hashes = b.column("hash").to_numpy()
            for first, last in groups(texts, CUT_BYTES):
                if reader.full() and len(counts):  # it may be full from a former task, before this one has counts
                    yield from counted()
                    counts = counts[:0]
                at, many = reader.numbers(texts.slice(first, last - first))
                words, part = reader.encoder.words, parts[first:last]
                new = np.bincount(at[np.repeat(part < ROUNDS, many)], minlength=len(words))
                new[: len(counts)] += counts
                counts = new
                # texts of one part together, cut into records
                order, begin = np.argsort(part, kind="stable"), np.cumsum(many) - many
                many, part = many[order], part[order]
                stops = np.cumsum(many)
                at = at[np.repeat(begin[order] - stops + many, many) + np.arange(stops[-1])]
                bounds = np.flatnonzero(np.diff((stops - many) // RECORD_WORDS * (ROUNDS + 1) + part, prepend=-1, append=-1))
                if named is not words:
                    names, named = [], words
                names.extend([w or "" for w in islice(words.number, len(names), None)])
                place = np.empty(len(words), np.int32)
                out = {k: [] for k in ("part", "hash", "many", "at", "sizes", "ids", "words")}
                for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                    here = at[stops[lo] - many[lo] : stops[hi - 1]]
                    flag = np.zeros(len(words), bool)
                    flag[here] = True
                    own = np.flatnonzero(flag)
                    place[own] = np.arange(len(own), dtype=np.int32)
                    ids, sizes = words.spelled(own)
                    out["part"].append(int(part[lo]))
                    out["hash"].append(_small(hashes[first:last][order[lo:hi]].view(np.uint64)))
                    out["many"].append(_small(many[lo:hi]))
                    out["at"].append(_small(place[here]))
                    out["sizes"].append(_small(sizes))
                    out["ids"].append(_small(ids))
                    out["words"].append(" ".join(map(names.__getitem__, own.tolist())).encode())
                doc = pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), b.column("doc_id").slice(first, last - first).take(pa.array(order)))
                yield rows(len(out["part"]), part=pa.array(out["part"], pa.int32()), doc=doc, **{k: pa.array(v, pa.binary()) for k, v in out.items() if k != "part"})
        if len(counts):
            yield from counted()

    return staged(hashed.mapInArrow(run, schema), "lm-cut")


def records(b: pa.RecordBatch, model: Attention):
    """(texts, their dictionary's spellings, first and last row) of runs of records of about GROUP_WORDS words."""
    total, last = np.cumsum([m.sum() for m in _joined(b.column("many"), 0, b.num_rows)]), 0
    while last < b.num_rows:
        first, last = last, max(last + 1, int(np.searchsorted(total, (total[last - 1] if last else 0) + GROUP_WORDS, "right")))
        ids, sizes, at, many = (_joined(b.column(k), first, last) for k in ("ids", "sizes", "at", "many"))
        before = np.cumsum([0, *map(len, sizes)])
        own = Spellings.of(np.concatenate(ids), np.concatenate(sizes).astype(np.int64))
        yield placed(model, own, np.concatenate([a + n for a, n in zip(at, before)]), np.concatenate(many).astype(np.int64)), own, first, last


def learn(cuts: DataFrame, model: Attention) -> Attention:
    """The model trained on the training records of ``cut``, a part of them a round."""
    spark = cuts.sparkSession
    for nth in range(ROUNDS):
        shared, rate = spark.sparkContext.broadcast(model), ROUND_RATE * (1 - nth / ROUNDS)

        def run(batches, shared=shared, rate=rate, nth=nth):
            model, r, done = copy.deepcopy(shared.value), np.random.default_rng([nth, TaskContext.get().partitionId()]), 0
            for b in batches:
                for t, _, first, last in records(b, model):
                    hashes = np.abs(np.concatenate(_joined(b.column("hash"), first, last)).astype(np.uint64).view(np.int64) >> 8)
                    done += train(model, t, trained_windows(t, hashes), rate, r)
            if done:
                w = np.append(model.flat().astype(np.float64) * done, done)
                yield pa.RecordBatch.from_arrays([pa.array([w.astype("<f8").tobytes()], pa.binary())], names=["weights"])

        def summed(batches):
            total = None
            for b in batches:
                for w in b.column("weights"):
                    w = np.frombuffer(w.as_buffer(), "<f8")
                    total = w.copy() if total is None else total + w
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], names=["weights"])

        weights = staged(cuts.where(F.col("part") == nth).select("hash", "many", "at", "sizes", "ids").mapInArrow(run, "weights binary"), "lm-round")
        got = weights.repartition(AVERAGERS).mapInArrow(summed, "weights binary").collect()
        if got:
            total = sum(np.frombuffer(g["weights"], "<f8") for g in got)
            model.load(total[:-1] / total[-1])
    return model


def summed_counts(cuts: DataFrame) -> DataFrame:
    """Staged counts of the distinct words, a row for each bucket."""

    def run(table):
        words = _words(table).dictionary_encode()
        at = words.indices.to_numpy()
        c, one = np.bincount(at, _whole(table, "c")), np.empty(len(words.dictionary), np.int64)
        one[at] = np.arange(len(at))
        ids, sizes = Spellings.of(_whole(table, "key_ids"), _whole(table, "id_sizes").astype(np.int64)).spelled(one)
        flat, lengths = _flat(words.dictionary)
        columns = [flat.tobytes(), *map(_small, (lengths, c.astype(np.int64), sizes, ids))]
        return pa.table([table.column("bucket").slice(0, 1), *(pa.array([v], pa.binary()) for v in columns)], names=table.column_names)

    names = [f.split(" ")[0] for f in COUNTS.split(", ")]
    return staged(cuts.where("bucket IS NOT NULL").select(*names).groupBy("bucket").applyInArrow(run, COUNTS), "word-counts")


def listed(counts: DataFrame, least: int = 0) -> DataFrame:
    """(word, c) of the words that occur ``least`` times or more."""

    def run(batches):
        for b in batches:
            c = _whole(b, "c").astype(np.int64)
            some = np.flatnonzero(c >= least)
            yield pa.RecordBatch.from_arrays([_words(b).take(pa.array(some)).cast(pa.binary()).cast(pa.string()), pa.array(c[some])], names=["word", "c"])

    return counts.select("keys", "key_sizes", "c").mapInArrow(run, "word string, c long")


def count_steps(counts: DataFrame) -> list:
    """(step, k, c), the largest step first: k words occur 2^step times or more, but less than twice that, c times in all."""

    def run(batches):
        for b in batches:
            c = _whole(b, "c").astype(np.int64)
            step = np.frexp(c)[1] - 1
            k, total = np.bincount(step, minlength=1), np.bincount(step, c, 1)
            some = np.flatnonzero(k)
            yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array(k[some]), pa.array(total[some].astype(np.int64))], names=["step", "k", "c"])

    rows = counts.select("c").mapInArrow(run, "step int, k long, c long")
    return rows.groupBy("step").agg(F.sum("k").alias("k"), F.sum("c").alias("c")).orderBy(F.desc("step")).collect()


def mean_shares(model: Attention, counts: DataFrame, ends: int) -> np.ndarray:
    """pi: mean shares of the states over the smoothed corpus shares of all words with ids, the end included."""
    shared = counts.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        model, total = shared.value, np.zeros(STATES)
        for b in batches:
            for k in range(b.num_rows):
                row = b.slice(k, 1)
                sizes = _whole(row, "id_sizes").astype(np.int64)
                total += ((sizes > 0) * (_whole(row, "c") + 0.5)) @ softmax(model.own(_whole(row, "key_ids"), sizes))
        yield pa.RecordBatch.from_arrays([pa.array(range(STATES), pa.int32()), pa.array(total)], names=["state", "mass"])

    total = softmax(model.own(np.array([model.end]), np.array([1])))[0] * (ends + 0.5)
    for state, mass in counts.select("c", "id_sizes", "key_ids").mapInArrow(run, "state int, mass double").groupBy("state").agg(F.sum("mass").alias("mass")).collect():
        total[state] += mass
    return total / total.sum()


@dataclass
class Fitted:
    model: Attention
    pi: np.ndarray
    words: DataFrame  # (word, c)
    counts: DataFrame  # ``summed_counts``
    buckets: int
    ends: int
    tokens: int
    below: float  # log10 of the denominator of the corpus shares
    shares: dict  # log10 corpus shares of the frequent words and of the end


def fit(training: DataFrame, tokenizer: str, cuts: DataFrame | None = None) -> Fitted:
    """training: (doc_id, text); cuts: ``cut`` of them and maybe of others."""
    model = warm_start(training, tokenizer)
    cuts = cuts or cut(training, tokenizer, F.lit(True))
    model = learn(cuts, model)
    counts, ends = summed_counts(cuts), cuts.agg(F.sum("ends")).first()[0] or 0
    steps = count_steps(counts)
    tokens, distinct = sum(r["c"] for r in steps) + ends, sum(r["k"] for r in steps) + (ends > 0)
    cut_step, room = 62, WORDS_MOST
    for r in steps:
        if r["k"] > room:
            break
        cut_step, room = r["step"], room - r["k"]
    below = math.log10(tokens + 0.5 * (distinct + 1))
    frequent = listed(counts, 2**cut_step).toArrow()
    shares = dict(zip(frequent.column("word").to_pylist(), (np.log10(frequent.column("c").to_numpy() + 0.5) - below).tolist()))
    shares[""] = math.log10(ends + 0.5) - below
    return Fitted(model, mean_shares(model, counts, ends), listed(counts), counts, buckets_of(training), ends, tokens, below, shares)


def tilts(model: Attention, pi: np.ndarray, words: Spellings) -> np.ndarray:
    """r / pi by number of a word; one where a word has no ids."""
    out = softmax(model.own(words.ids, words.sizes)) / pi.astype(np.float32)
    out[words.sizes == 0] = 1.0
    return out


def rare_shares(rare: DataFrame, f: Fitted) -> DataFrame:
    """(row, more, also): sums of the log shares of the rare words of a row, and how many were met in training.

    rare: (bucket, chunk, keys, key_sizes, at, times), words of the rows chunk + at.
    """
    below = f.below

    def answered(rare, counts):
        if not rare.num_rows:
            return ANSWERS.empty_table()
        many, times = np.array([len(_large(v)) for v in rare.column("key_sizes").to_pylist()]), _whole(rare, "times").astype(np.int64)
        known = _words(counts)
        c = np.append(_whole(counts, "c"), 0)[pc.fill_null(pc.index_in(_words(rare), known), len(known)).to_numpy()]
        columns = [_parts(times * (np.log10(c + 0.5) - below), many, np.ndarray.tobytes), _parts(np.where(c > 0, times, 0), many)]
        return pa.table([rare.column("chunk"), rare.column("at"), *columns], names=["chunk", "at", "more", "also"])

    def summed(table):
        at = _whole(table, "at")
        more, also = np.bincount(at, np.frombuffer(b"".join(table.column("more").to_pylist()))), np.bincount(at, _whole(table, "also"))
        some = np.flatnonzero(np.bincount(at))
        return pa.table([pa.array(table.column("chunk")[0].as_py() + some), pa.array(more[some]), pa.array(also[some].astype(np.int64))], names=["row", "more", "also"])

    ANSWERS = pa.schema({"chunk": pa.int64(), "at": pa.binary(), "more": pa.binary(), "also": pa.binary()})
    answers = rare.groupBy("bucket").cogroup(f.counts.select("bucket", "keys", "key_sizes", "c").groupBy("bucket")).applyInArrow(answered, "chunk long, at binary, more binary, also binary")
    return answers.groupBy("chunk").applyInArrow(summed, "row long, more double, also long")


def scored(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", fitted: Fitted | None = None) -> DataFrame:
    """Per document: held_out, n_tokens, n_known, train_tokens, base_score, score, context_gain."""
    d = docs.select(docs[id_col].alias("doc_id"), docs[text_col].cast("string").alias("text"))
    cuts = cut(d, tokenizer, ~held_out(F.col("doc_id")))
    f = fitted or fit(d.where(~held_out(F.col("doc_id"))), tokenizer, cuts)
    ends, buckets, rare_most = f.ends, f.buckets, RARE_MOST
    shared = d.sparkSession.sparkContext.broadcast((f.model, f.pi, list(f.shares), np.array([*f.shares.values(), math.nan])))

    def run(batches):
        model, pi, frequent, shares = shared.value
        w, task, nth = model.prepared(), TaskContext.get().partitionId(), 0
        frequent = pa.array(frequent, pa.large_string())
        kept, chunk = [], nth  # rare words since row ``chunk``: (words, row from there, times)

        def sent():
            words, at, times = (pa.concat_arrays(k) if isinstance(k[0], pa.Array) else np.concatenate(k) for k in zip(*kept))
            order, many, columns = dealt(words, buckets)
            columns |= {"chunk": pa.array(np.full(len(many), (task << 40) + chunk)), "at": _parts(at[order], many), "times": _parts(times[order], many)}
            return pa.RecordBatch.from_arrays([columns.get(k, pa.nulls(len(many), t)) for k, t in types.items()], names=list(types))

        types = None
        for b in batches:
            types = types or {"row": pa.int64(), "doc_id": b.schema.field("doc").type.value_type, "n_tokens": pa.int64(), "n_known": pa.int64(), "base": pa.float64(), "gain": pa.float64(),
                              "chunk": pa.int64(), "bucket": pa.int32(), **dict.fromkeys(("keys", "key_sizes", "at", "times"), pa.binary())}
            names = pc.split_pattern(b.column("words").cast(pa.large_binary()).cast(pa.large_string()), " ")
            logs = shares[pc.fill_null(pc.index_in(names.values, frequent), len(frequent)).to_numpy()]  # by word of all records
            for t, own, first, last in records(b, model):
                here, to = names.offsets[first].as_py(), names.offsets[last].as_py()
                u, n = logs[here:to][t.at], len(t.many)
                known = ~np.isnan(u)
                gain = gains(model, t, tilts(model, pi, own), w) if ends else np.zeros(len(u))
                columns = {"row": pa.array((task << 40) + np.arange(nth, nth + n)), "doc_id": b.column("doc").slice(first, last - first).flatten(), "n_tokens": pa.array(t.many),
                           "n_known": pa.array(segment_sums(known.astype(np.int64), t.many) - (ends == 0)), "base": pa.array(segment_sums(np.where(known, u, 0.0), t.many)), "gain": pa.array(segment_sums(gain, t.many))}
                yield pa.RecordBatch.from_arrays([columns.get(k, pa.nulls(n, kind)) for k, kind in types.items()], names=list(types))
                rare = np.flatnonzero(~known)
                if len(rare):
                    key, times = np.unique(np.repeat(np.arange(n), t.many)[rare] << 32 | t.at[rare], return_counts=True)
                    kept.append((names.values.take(pa.array(here + (key & 0xFFFFFFFF))), nth - chunk + (key >> 32), times))
                nth += n
                if sum(len(k[1]) for k in kept) > rare_most:
                    yield sent()
                    kept, chunk = [], nth
        if kept:
            yield sent()

    id_type = docs.schema[id_col].dataType.simpleString()
    read = cuts.where("part IS NOT NULL").select("doc", "many", "at", "sizes", "ids", "words")
    both = staged(read.mapInArrow(run, f"row long, doc_id {id_type}, n_tokens long, n_known long, base double, gain double, chunk long, bucket int, keys binary, key_sizes binary, at binary, times binary"), "lm-scores")
    more = rare_shares(both.where("bucket IS NOT NULL").select("bucket", "chunk", "keys", "key_sizes", "at", "times"), f)
    out = both.where("row IS NOT NULL").join(more, "row", "left").withColumn("base_score", F.col("base") + F.coalesce("more", F.lit(0.0)))
    return out.select(
        "doc_id", held_out(F.col("doc_id")).alias("held_out"), "n_tokens", (F.col("n_known") + F.coalesce("also", F.lit(0))).cast("long").alias("n_known"),
        F.lit(f.tokens).cast("long").alias("train_tokens"), "base_score", (F.col("base_score") + F.col("gain")).alias("score"), F.col("gain").alias("context_gain"))


def op9(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return scored(read_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
