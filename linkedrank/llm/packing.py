"""Operator 2: best-fit packing of token pieces after dominance reduction.

Pieces only differ by length, so the packing is solved on the histogram of lengths (at most
``capacity`` entries, whatever the corpus holds) and laid out as runs: "pieces of length L
with ranks r .. r+n-1 go to sequences s .. s+n-1 at offset o". A piece finds its run from its
length and its rank among pieces of that length; ranks are counted within the tasks that cut
the pieces and shifted by per-task totals, so no task ever gathers one length.

The solver first fixes sets that dominate every alternative: a piece with which nothing else
fits; a pair that fills a sequence; a pair when no two others fit beside the piece; a pair when
no three others fit and no fitting two others hold more than its partner. An optimal packing
contains such sets, so fixing them loses nothing. The rest is packed best-fit decreasing.

Edge cases: a null or empty text is the end id alone; repeated rows are packed once per row;
null ids are carried; an empty table gives an empty result; texts of any length are cut into
full pieces with one shorter last piece; extra columns are ignored.
"""

from __future__ import annotations

import gc
import json
import re
import zlib
from bisect import bisect_left, insort
from itertools import repeat

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from linkedrank.sources import read_table, staged

CAPACITY = 4096
END_ID = 1
HELD_MOST = 250_000  # words, and atoms, that a worker remembers before it starts anew
GROUP_BYTES = 3_000_000  # of text that is split into words at a time
PIECE_SCHEMA = "piece int, start long, length long, ids_crc32 long"
_encoders: dict = {}

# Of plain words in lower case, the tokenizer's own split into letters, single digits and signs; blanks part words.
_ATOMS = re.compile(r" |'s|'t|'re|'ve|'m|'ll|'d|[a-z\xdf-\xf6\xf8-\xff]+|[0-9]|[^ a-z0-9\xdf-\xf6\xf8-\xff]+")


def _plain(joined: str, many: int) -> np.ndarray:
    """Which of the words, joined by blanks, are plain: of ASCII signs and Latin-1 letters only, of which
    lower case and composed form are plain too, and without the start of a control string."""
    u = np.frombuffer(joined.encode(), np.uint8)
    before = np.concatenate([[np.uint8(32)], u[:-1]])
    letter = (u >= 0x80) & (u <= 0xBF) & (before == 0xC3) & (u != 0x97) & (u != 0xB7)
    bad = ~((u >= 32) & (u < 127) | (u == 0xC3) | letter) | ((u == 124) & (before == 60))
    out = np.ones(many, bool)
    out[np.cumsum(u == 32)[bad]] = False
    return out


def _byte_letters() -> str:
    """The letter that stands for each byte in a byte-level vocabulary: itself where it prints,
    else the next unused one from U+0100 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = iter(range(256, 512))
    return "".join(chr(b) if b in shown else chr(next(other)) for b in range(256))


_LETTERS = _byte_letters()


class Spellings:
    """Keys by number, and the ids of each number in one row of ids."""

    def __init__(self):
        self.number: dict = {}
        self.ids, self.sizes, self.starts = np.empty(0, np.uint32), np.empty(0, np.int64), np.empty(0, np.int64)

    @classmethod
    def of(cls, ids: np.ndarray, sizes: np.ndarray) -> Spellings:
        """Spellings of numbers alone, without keys."""
        out = cls()
        out.ids, out.sizes, out.starts = ids, sizes, np.cumsum(sizes) - sizes
        return out

    def __len__(self) -> int:
        return len(self.number)

    def find(self, keys: list) -> np.ndarray:
        """Numbers of the keys, -1 where unknown."""
        return np.fromiter(map(self.number.get, keys, repeat(-1)), np.int64, len(keys))

    def add(self, keys: list, ids: np.ndarray, sizes: np.ndarray) -> None:
        self.starts = np.concatenate([self.starts, len(self.ids) + np.cumsum(sizes) - sizes])
        self.sizes = np.concatenate([self.sizes, sizes])
        self.ids = np.concatenate([self.ids, ids])
        self.number.update(zip(keys, range(len(self.number), len(self.number) + len(keys))))

    def spelled(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of numbered keys in one row, and the ids of each."""
        sizes = self.sizes[at]
        stops = np.cumsum(sizes)
        return self.ids[np.repeat(self.starts[at] - stops + sizes, sizes) + np.arange(stops[-1] if len(stops) else 0)], sizes


def segment_sums(values: np.ndarray, many: np.ndarray) -> np.ndarray:
    """Sums of consecutive runs of ``values``; run k holds many[k] of them, none too."""
    total = np.concatenate([np.zeros(1, values.dtype), np.cumsum(values)])
    stops = np.cumsum(many)
    return total[stops] - total[stops - many]


class Merges:
    """The tokenizer's merges, applied to many atoms at a time: atoms of one length are a matrix, and
    each round merges the leftmost pair of lowest rank in every row that still has one."""

    LONGEST, NONE, BITS = 48, 1 << 30, 19

    def __init__(self, model: dict):
        vocab, self.size = model["vocab"], len(model["vocab"])
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        keys = np.array([vocab[a] * self.size + vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(keys)
        self.keys, self.ranks = np.append(keys[order], 1 << 62), np.append(order, self.NONE).astype(np.int64)
        self.into = np.array([vocab[a + b] for a, b in pairs] + [0], np.int64)  # by rank
        # most pairs are looked up at a hashed place; those that share one, and what falls there, are searched for
        place = self._place(self.keys[:-1])
        self.hashed, shared = np.full(1 << self.BITS, len(self.keys) - 1, np.int32), np.bincount(place, minlength=1 << self.BITS) > 1
        self.hashed[place] = np.arange(len(self.keys) - 1)
        self.hashed[shared] = -1
        self.first = np.array([[vocab[c + end] for c in _LETTERS] for end in ("", "</w>")], np.int64)

    def _rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left * self.size + right
        at = self.hashed.take(self._place(key))
        shared = np.nonzero(at < 0)
        if len(shared[0]):
            at[shared] = np.searchsorted(self.keys, key[shared])
        return np.where(self.keys.take(at) == key, self.ranks.take(at), self.NONE)

    def _place(self, key: np.ndarray) -> np.ndarray:
        return (key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.BITS)).view(np.int64)

    def apply(self, coded: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all atoms (UTF-8, none empty or longer than LONGEST) in one row, and the ids of each."""
        lengths = np.fromiter(map(len, coded), np.int64, len(coded))
        flat, starts = np.frombuffer(b"".join(coded), np.uint8), np.cumsum(lengths) - lengths
        sizes, done = np.zeros(len(coded), np.int64), []
        for length in np.unique(lengths).tolist():
            atom = np.flatnonzero(lengths == length)
            ids = flat[starts[atom][:, None] + np.arange(length)]
            ids = np.concatenate([self.first[0][ids[:, :-1]], self.first[1][ids[:, -1:]]], axis=1)
            rank = self._rank(ids[:, :-1], ids[:, 1:])
            while ids.shape[1] > 1:
                at = rank.argmin(axis=1)
                low = rank[np.arange(len(at)), at]
                stop = low == self.NONE
                if stop.any():
                    done.append((atom[stop], ids[stop]))
                    atom, ids, rank, at, low = atom[~stop], ids[~stop], rank[~stop], at[~stop], low[~stop]
                rows, n = np.arange(len(at)), ids.shape[1]
                ids = ids[rows[:, None], np.arange(n - 1) + (np.arange(n - 1) > at[:, None])]
                ids[rows, at] = self.into[low]
                rank = rank[rows[:, None], np.arange(n - 2) + (np.arange(n - 2) >= at[:, None])]
                for shift in (-1, 0):  # the merged id's pairs with its neighbours
                    near = at + shift
                    ok = np.flatnonzero((near >= 0) & (near < n - 2))
                    rank[ok, near[ok]] = self._rank(ids[ok, near[ok]], ids[ok, near[ok] + 1])
            done.append((atom, ids))
        for atom, ids in done:
            sizes[atom] = ids.shape[1]
        out, begin = np.empty(int(sizes.sum()), np.uint32), np.cumsum(sizes) - sizes
        for atom, ids in done:
            out[begin[atom][:, None] + np.arange(ids.shape[1])] = ids
        return out, sizes


class Encoder:
    """Token ids of words; the tokenizer never merges over blanks, so words are encoded once and
    remembered by number. Plain words are put together from the letters and signs they hold (atoms),
    which recur far more often than the words do."""

    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer, self.words, self.atoms = Tokenizer.from_file(path), Spellings(), Spellings()
        self.size = self.tokenizer.get_vocab_size()
        self.merges = Merges(json.loads(self.tokenizer.to_str())["model"])

    @classmethod
    def at(cls, path: str) -> Encoder:
        if path not in _encoders:
            _encoders[path] = cls(path)
        return _encoders[path]

    def numbers(self, words: list[str]) -> np.ndarray:
        """Numbers of distinct words without blanks; they hold until the next call."""
        if len(self.words) > HELD_MOST:
            self.words = Spellings()
        at = self.words.find(words)
        missing = np.flatnonzero(at < 0)
        if len(missing):
            collecting = gc.isenabled()
            gc.disable()  # nothing here makes cycles, and collections would walk all short-lived lists
            try:
                at[missing] = self._learn([words[k] for k in missing])
            finally:
                if collecting:
                    gc.enable()
        return at

    def spell(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words in one row, and the ids of each; nothing is remembered of the words."""
        joined, sizes = " ".join(words), np.zeros(len(words), np.int64)
        plain = _plain(joined, len(words))
        parts = _ATOMS.findall((joined if plain.all() else " ".join([w for w, p in zip(words, plain) if p])).lower())
        if len(self.atoms) > HELD_MOST:
            self.atoms = Spellings()
        at = self.atoms.find(parts)
        missing = np.flatnonzero(at < 0).tolist()
        if missing:
            lacking = [parts[k] for k in missing]
            new = set(lacking)
            if " " in new:
                self.atoms.add([" "], np.empty(0, np.uint32), np.zeros(1, np.int64))
            new.discard(" ")
            short, long = list(new), []
            coded = " ".join(short).encode().split(b" ") if short else []  # no other atom holds a blank
            if coded and max(map(len, coded)) > Merges.LONGEST:
                long = [(k, c) for k, c in zip(short, coded) if len(c) > Merges.LONGEST]
                short, coded = [k for k, c in zip(short, coded) if len(c) <= Merges.LONGEST], [c for c in coded if len(c) <= Merges.LONGEST]
            self.atoms.add(short, *self.merges.apply(coded))
            for k, c in long:
                ids = [t.id for t in self.tokenizer.model.tokenize(c.decode("latin-1").translate(_LETTERS))]
                self.atoms.add([k], np.array(ids, np.uint32), np.array([len(ids)]))
            at[missing] = self.atoms.find(lacking)
        ids, each = self.atoms.spelled(at)
        if plain.any():
            word = np.cumsum(at == self.atoms.number.get(" ", -1))  # a blank has no ids
            sizes[plain] = np.bincount(word, each, int(plain.sum())).astype(np.int64)
        if not plain.all():
            coded = [e.ids for e in self.tokenizer.encode_batch_fast([w for w, p in zip(words, plain) if not p], add_special_tokens=False)]
            sizes[~plain] = [len(c) for c in coded]
            whole, own = np.empty(int(sizes.sum()), np.uint32), np.repeat(plain, sizes)
            whole[own] = ids
            whole[~own] = [i for c in coded for i in c]
            ids = whole
        return ids, sizes

    def _learn(self, new: list[str]) -> np.ndarray:
        first = len(self.words)
        self.words.add(new, *self.spell(new))
        return np.arange(first, len(self.words))

    def split(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the words of all texts in one row, and the words of each text."""
        lists = pc.ascii_split_whitespace(texts)
        words = lists.flatten().dictionary_encode()
        at = self.numbers(words.dictionary.to_numpy(zero_copy_only=False).tolist())
        return at[words.indices.to_numpy(zero_copy_only=False)] if len(words) else np.empty(0, np.int64), pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)


def text_column(batch: pa.RecordBatch, name: str) -> pa.Array:
    """A column of texts with null as the empty text."""
    return pc.fill_null(batch.column(name).cast(pa.large_string()), "")


def groups(texts: pa.Array, most: int = GROUP_BYTES):
    """(start, end) of runs of texts of about ``most`` bytes, at least one text each."""
    total = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False))
    start = 0
    while start < len(texts):
        end = max(start + 1, int(np.searchsorted(total, (total[start - 1] if start else 0) + most, "right")))
        yield start, end
        start = end


def pieces(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text",
           capacity: int = CAPACITY, end_id: int = END_ID, with_ids: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
    """Pieces of at most ``capacity`` ids; ``task`` and ``nth`` number equal lengths within a task.

    keep: further columns of ``docs`` that the pieces carry.
    """
    d = docs.select(docs[id_col].alias("doc_id"), docs[text_col].cast("string").alias("text"), *[docs[c] for c in keep])
    carried = "".join(f", `{f.name}` {f.dataType.simpleString()}" for f in d.schema.fields if f.name in keep)
    names = ["piece", "start", "length", "ids_crc32", "task", "nth"]

    def cut(batches):
        encoder, seen, task = Encoder.at(tokenizer), np.zeros(capacity + 1, dtype=np.int64), TaskContext.get().partitionId()
        for batch in batches:
            texts = text_column(batch, "text")
            for first, last in groups(texts):
                at, many = encoder.split(texts.slice(first, last - first))
                ids, sizes = encoder.words.spelled(at)
                stops = np.cumsum(segment_sums(sizes, many))
                ids = np.insert(ids, stops, end_id).astype("<u4", copy=False)
                stops += np.arange(1, len(stops) + 1)
                totals = np.diff(stops, prepend=0)
                per = -(-totals // capacity)
                doc = np.repeat(np.arange(len(totals)), per)
                piece = np.arange(len(doc)) - np.repeat(np.cumsum(per) - per, per)
                start = piece * capacity
                length = np.minimum(capacity, totals[doc] - start)
                begin = (stops - totals)[doc] + start
                view, crc, nth = memoryview(ids).cast("B"), [], []
                for b, n in zip(begin.tolist(), length.tolist()):
                    crc.append(zlib.crc32(view[4 * b : 4 * (b + n)]))
                    nth.append(int(seen[n]))
                    seen[n] += 1
                out = [pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array(crc, pa.int64()), pa.array(np.full(len(doc), task, np.int32)), pa.array(nth, pa.int64())]
                if with_ids:
                    out.append(pa.array([ids[b : b + n].astype(np.int64) for b, n in zip(begin, length)], pa.list_(pa.int64())))
                rows = pa.array(first + doc)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(rows), *out, *[batch.column(c).take(rows) for c in keep]],
                                                 names=["doc_id", *names, *["ids"] * with_ids, *keep])

    id_type = docs.schema[id_col].dataType.simpleString()
    return d.mapInArrow(cut, f"doc_id {id_type}, {PIECE_SCHEMA}, task int, nth long" + ", ids array<long>" * with_ids + carried)


class Layout:
    """Runs (length, first rank, count, first sequence, offset) of a packing in the making."""

    def __init__(self):
        self.used: dict[int, int] = {}
        self.runs: list[tuple[int, int, int, int, int]] = []
        self.sequences = 0

    def add(self, contents: list[tuple[int, int]], copies: int) -> None:
        """``copies`` sequences with the same contents: (length, how many) in order."""
        offset = 0
        for length, many in contents:
            for _ in range(many):
                first = self.used.get(length, 0)
                self.runs.append((length, first, copies, self.sequences, offset))
                self.used[length] = first + copies
                offset += length
        self.sequences += copies


def _smallest(counts: dict[int, int], order: list[int], but: int) -> list[int]:
    """The three smallest lengths with multiplicity, without one piece of length ``but``."""
    out: list[int] = []
    for x in order:
        out += [x] * min(3 - len(out), counts[x] - (x == but))
        if len(out) == 3:
            break
    return out


def _best_pair(counts: dict[int, int], order: list[int], but: int, room: int) -> int:
    """Largest sum of two other lengths that fits ``room`` (0: none)."""
    best, i, j = 0, 0, bisect_left(order, room + 1) - 1
    have = lambda x: counts[x] - (x == but)
    while i <= j:
        s = order[i] + order[j]
        if s > room or not have(order[j]):
            j -= 1
        else:
            if have(order[i]) and (i != j or have(order[i]) > 1):
                best = max(best, s)
            i += 1
    return best


def reduce_by_dominance(counts: dict[int, int], capacity: int, layout: Layout) -> None:
    """Fix dominating sets in ``layout`` and take them out of ``counts``."""
    order = sorted(counts)

    def take(length: int, n: int) -> None:
        counts[length] -= n
        if not counts[length]:
            del counts[length]
            order.pop(bisect_left(order, length))

    changed = True
    while changed:
        changed = False
        for length in order[::-1]:
            while length in counts:
                n, room = counts[length], capacity - length
                low = _smallest(counts, order, length)
                if not low or low[0] > room:
                    layout.add([(length, 1)], n)
                    take(length, n)
                    changed = True
                    break
                at = bisect_left(order, room + 1) - 1
                if order[at] == length and n == 1:
                    at -= 1
                mate = order[at]
                two, three = sum(low[:2]), sum(low)
                if not (mate == room or len(low) < 2 or two > room
                        or ((len(low) < 3 or three > room) and _best_pair(counts, order, length, room) <= mate)):
                    break
                if mate == length:
                    layout.add([(length, 2)], n // 2)
                    take(length, n // 2 * 2)
                else:
                    m = min(n, counts[mate])
                    layout.add([(length, 1), (mate, 1)], m)
                    take(length, m)
                    take(mate, m)
                changed = True


def best_fit(counts: dict[int, int], capacity: int, layout: Layout) -> None:
    """Best-fit decreasing on multiplicities: equal open sequences are handled together."""
    open_at: dict[int, list[list]] = {}  # room left -> [[contents, copies], ...]
    rooms: list[int] = []

    def put(room: int, contents: list, copies: int) -> None:
        if copies:
            if room not in open_at:
                open_at[room] = []
                insort(rooms, room)
            open_at[room].append([contents, copies])

    for length in sorted(counts, reverse=True):
        left = counts[length]
        while left:
            at = bisect_left(rooms, length)
            if at == len(rooms):
                room, contents, copies = capacity, [], left // (capacity // length) + 1
            else:
                room = rooms[at]
                contents, copies = open_at[room].pop()
                if not open_at[room]:
                    del open_at[room]
                    rooms.pop(at)
            fill = room // length
            full = min(copies, left // fill)
            put(room - fill * length, contents + [(length, fill)], full)
            left -= full * fill
            if full < copies and left:  # fewer than fill pieces are left: one more sequence takes them
                put(room - left * length, contents + [(length, left)], 1)
                full, left = full + 1, 0
            if contents:
                put(room, contents, copies - full)
    for groups in open_at.values():
        for contents, copies in groups:
            layout.add(contents, copies)


def solve(histogram: dict[int, int], capacity: int = CAPACITY) -> Layout:
    counts, layout = {k: v for k, v in histogram.items() if v}, Layout()
    reduce_by_dominance(counts, capacity, layout)
    best_fit(counts, capacity, layout)
    return layout


def place(cut: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Add sequence_id and offset to staged ``pieces``."""
    spark = cut.sparkSession
    totals = cut.groupBy("length", "task").agg(F.count("*").alias("n"))
    w = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, 0)
    shift = totals.withColumn("shift", F.sum("n").over(w) - F.col("n")).drop("n")
    layout = solve({r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}, capacity)
    runs = np.array(sorted(layout.runs), dtype=np.int64).reshape(-1, 5)
    shared = spark.sparkContext.broadcast(runs)  # under capacity^1.5 runs, whatever the corpus holds

    def assign(batches):
        r = shared.value
        key = r[:, 0] << 44 | r[:, 1]
        for b in batches:
            rank = (b["shift"] + b["nth"]).to_numpy(np.int64)
            at = np.searchsorted(key, b["length"].to_numpy(np.int64) << 44 | rank, side="right") - 1
            b["sequence_id"] = r[at, 3] + rank - r[at, 1]
            b["offset"] = r[at, 4]
            yield b.drop(columns=["shift", "nth", "task"])

    kept = [f for f in cut.schema.fields if f.name not in ("nth", "task")]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept) + ", sequence_id long, offset long"
    joined = cut.join(shift, ["length", "task"]).select(*[f.name for f in kept], "task", "nth", "shift")
    return joined.mapInPandas(assign, schema)


def pack(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, **columns) -> DataFrame:
    """Cut, solve and place all documents."""
    return place(staged(pieces(docs, tokenizer, capacity=capacity, **columns), "pieces"), capacity)


def op2(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(read_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
