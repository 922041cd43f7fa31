"""Suffix-array dedup by prefix-free parsing.

A rolling hash of ``TRIGGER`` bytes cuts every document at content-defined triggers; a phrase runs from one trigger to the
end of the next, so equal strings contain equal phrases. A string of ``length`` bytes can stand elsewhere only if all
phrases inside it do; a first exchange counts the phrases of the corpus and leaves the stretches where that holds.

Stretches are cut where the rarest phrase inside the running window changes, and dealt out by that phrase, so equal windows
meet in one bucket whatever surrounds them. There, equal pieces collapse (highly repetitive text shrinks to its distinct parts),
and the rest is parsed again: suffixes of the dictionary of distinct phrases are ranked by prefix doubling, so are the suffixes of
the parse (pieces as sequences of phrase ranks), and the pair (rank of the phrase suffix at a byte, rank of the parse behind it)
puts all bytes into the order of the text's suffixes. A window is repeated if a neighbour in that order has the same ``length`` bytes, which
two independent hashes of them decide.

Windows without a whole phrase inside, or with only phrases that stand more than 2**HOT times, are dealt out one by one by their own hash instead, so
no phrase gathers an unbounded group.

Copies of a text are looked at once. Nulls and texts shorter than ``length`` lose nothing. Repeated rows are copies. An empty table gives
an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import exchange, flat
from .common import durable, table, width
from .substring import NOTHING, covered

TRIGGER = 8
EVERY = 40  # mean phrase length
HOT = 12
TOGETHER = 1 << 20  # bytes of pieces whose suffixes are ordered at once, unless one phrase deals out more
LIMIT = np.uint64((1 << 64) // EVERY)


class Parse:
    """Texts as bytes in one array with their phrases [a, b)."""

    def __init__(self, texts: list[bytes], length: int):
        self.length = length
        self.raw = np.frombuffer(b"".join(texts), np.uint8)
        self.at = np.concatenate([[0], np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)))])
        self.size = np.diff(self.at)
        self.runs = flat.Runs(flat.letters(31)[self.raw], 31)
        start = np.arange(max(0, len(self.raw) - TRIGGER + 1))
        t = np.flatnonzero(self.runs(start, start + TRIGGER) < LIMIT)
        doc = np.searchsorted(self.at, t, side="right") - 1
        inside = (t + TRIGGER <= self.at[doc + 1]) & (self.size[doc] >= length)
        self.trigger, self.trigger_doc = t[inside], doc[inside]
        same = self.trigger_doc[1:] == self.trigger_doc[:-1]
        self.a, self.b = self.trigger[:-1][same], self.trigger[1:][same] + TRIGGER
        self.doc = self.trigger_doc[1:][same]

    def phrases(self) -> exchange.Values:
        return exchange.Values(self.runs(self.a, self.b), np.bincount(self.doc, minlength=len(self.size)))

    def pieces(self, count: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """first start, last start + 1, dealing value (0: one by one), document. count: note of each phrase."""
        n, edge = self.length, np.zeros(len(self.raw) + 2, np.int64)
        lone = count == 0
        lo, hi = np.maximum(self.b[lone] - n, self.at[self.doc[lone]]), self.a[lone] + 1
        ok = lo < hi
        np.add.at(edge, lo[ok], 1)
        np.add.at(edge, hi[ok], -1)
        free = np.cumsum(edge[:-2]) == 0
        can = np.zeros(len(self.raw) + 1, np.int64)
        long = self.size >= n
        can[self.at[:-1][long]] += 1
        np.add.at(can, self.at[1:][long] - n + 1, -1)
        free &= np.cumsum(can[:-1]) > 0
        # break points: a phrase enters the window at b - n, leaves it after a; documents and free stretches begin and end
        turn = np.zeros(len(self.raw) + 1, bool)
        turn[self.a + 1] = True
        turn[np.maximum(self.b - n, 0)] = True
        turn[self.at] = True
        turn[1:-1] |= free[1:] != free[:-1]
        i = np.flatnonzero(turn[:-1] & free) if len(self.raw) else np.zeros(0, np.int64)
        stops = np.flatnonzero(turn | np.concatenate([[False] * len(self.raw), [True]]))
        j = stops[np.searchsorted(stops, i, side="right")] if len(i) else i
        first, last = np.searchsorted(self.a, i), np.searchsorted(self.b, i + n, side="right")
        value = self.runs(self.a, self.b)
        best = np.full(len(i), -1, np.int64)
        some = first < last
        if some.any():
            order = np.lexsort((value, count))
            rank = np.empty(len(order), np.int64)
            rank[order] = np.concatenate([[0], np.cumsum((value[order][1:] != value[order][:-1]) | (count[order][1:] != count[order][:-1]))])
            rank = rank * len(rank) + np.arange(len(rank))  # the leftmost of equal phrases
            levels = [rank]
            while (1 << len(levels)) <= int((last - first).max()):
                x, h = levels[-1], 1 << (len(levels) - 1)
                levels.append(np.minimum(x[: len(x) - h], x[h:]))
            k = np.log2(np.where(some, last - first, 1)).astype(np.int64)
            for level, x in enumerate(levels):
                m = some & (k == level)
                if m.any():
                    best[m] = np.minimum(x[first[m]], x[last[m] - (1 << level)]) % len(rank)
        hot = (best >= 0) & (count[np.maximum(best, 0)] > HOT) if len(count) else best >= 0
        best = np.where(hot, -1, best)
        doc = np.searchsorted(self.at, i, side="right") - 1
        new = np.concatenate([[True], (best[1:] != best[:-1]) | (i[1:] != j[:-1]) | (doc[1:] != doc[:-1])]) if len(i) else np.zeros(0, bool)
        head = np.flatnonzero(new)
        tail = np.append(head[1:], len(i)) - 1 if len(head) else head
        own = best[head]
        return i[head], j[tail], np.where(own >= 0, value[np.maximum(own, 0)] | np.uint64(1), np.uint64(0)) if len(value) else np.zeros(len(head), np.uint64), doc[head]


def phrase_values(length: int):
    return lambda texts, _=None: Parse(texts, length).phrases()


def how_often(values: np.ndarray, flags, ranks) -> np.ndarray:
    """0 for a phrase that stands once, else the digits of its count."""
    return np.ceil(np.log2(exchange.times(values["low"]))).astype(np.uint8)


def marked(length: int):
    """Pieces of texts from the phrase counts in `extra` (in text order)."""

    def cut(texts: list[bytes], notes: list[bytes]):
        p = Parse(texts, length)
        return p, p.pieces(np.concatenate([np.frombuffer(x, np.uint8) for x in notes]) if notes else np.zeros(0, np.uint8))

    return cut


def dealt_pieces(length: int):
    cut = marked(length)

    def run(texts, notes):
        p, (i, j, value, doc) = cut(texts, notes)
        keep = value > 0
        i, j, value, doc = i[keep], j[keep], value[keep], doc[keep]
        more = flat.Runs(flat.letters(33)[p.raw], 33)(i, j + length - 1)
        return flat.mix(value), more, np.bincount(doc, minlength=len(texts)), [p.raw[x : y + length - 1].tobytes() for x, y in zip(i.tolist(), j.tolist())]

    return run


def dealt_windows(length: int):
    cut = marked(length)

    def run(texts, notes):
        p, (i, j, value, doc) = cut(texts, notes)
        keep = value == 0
        n = (j - i)[keep]
        at = np.repeat(i[keep], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        return exchange.Values(flat.mix(p.runs(at, at + length)), np.bincount(np.repeat(doc[keep], n), minlength=len(texts)), more=flat.Runs(flat.letters(33)[p.raw], 33)(at, at + length))

    return run


def twice(values: np.ndarray, flags, ranks) -> np.ndarray:
    order = np.lexsort((values["more"], values["low"]))
    v = values[order]
    same = (v["low"][1:] == v["low"][:-1]) & (v["more"][1:] == v["more"][:-1])
    out = np.zeros(len(v), np.uint8)
    out[order] = np.concatenate([[False], same]) | np.concatenate([same, [False]]) if len(v) else 0
    return out


def doubled(symbols: np.ndarray, left: np.ndarray) -> np.ndarray:
    """Ranks of all suffixes of sequences that lie one after the other; left: symbols from each place to its sequence's end."""
    return _double(np.unique(symbols, return_inverse=True)[1] + 1, left, 1)


def _double(rank: np.ndarray, left: np.ndarray, k: int) -> np.ndarray:
    """From ranks by the first k symbols to ranks by all. A rank is the first place of its group in the order, so suffixes that are alone keep theirs."""
    longest = int(left.max()) if len(left) else 0
    open_ = np.argsort(rank)
    key, rank = rank[open_].astype(np.uint64), np.zeros(len(rank), np.int64)
    base, groups = np.int64(1), 1
    while len(open_):
        at, new = np.arange(len(key)), np.concatenate([[True], key[1:] != key[:-1]])
        rank[open_] = base + np.maximum.accumulate(np.where(new, at, 0))
        if k >= longest or int(new.sum()) == groups and groups > 1:  # nothing was split: later rounds split nothing either
            break
        alone = new & np.append(new[1:], True)
        open_ = open_[~alone]
        nxt, reach = np.zeros(len(open_), np.uint64), np.flatnonzero(left[open_] > k)
        nxt[reach] = rank[open_[reach] + k]
        key = rank[open_].astype(np.uint64) << np.uint64(32) | nxt
        order = np.argsort(key)
        open_, key, k = open_[order], key[order], 2 * k
        major = (key >> np.uint64(32)).astype(np.int64)
        head = np.concatenate([[True], major[1:] != major[:-1]]) if len(key) else np.zeros(0, bool)
        groups = int(head.sum())
        base = major - np.maximum.accumulate(np.where(head, np.arange(len(key)), 0)) if len(key) else major
    return rank


def left_of(lens: np.ndarray) -> np.ndarray:
    ends = np.cumsum(lens)
    return np.repeat(ends, lens) - np.arange(int(ends[-1]) if len(ends) else 0)


def suffix_order(bodies: list[bytes], length: int) -> tuple[np.ndarray, np.ndarray, flat.Runs, flat.Runs]:
    """Window starts of the bodies in the order of their suffixes, with the hashes to compare them."""
    p = Parse(bodies, length)
    # phrases of a body: from its begin or a trigger to the end of the next trigger or its own end
    t, td = p.trigger, p.trigger_doc
    per = np.bincount(td, minlength=len(bodies))
    first = np.cumsum(per + 1) - (per + 1)
    m = len(t) + len(bodies)
    a, b = np.empty(m, np.int64), np.empty(m, np.int64)
    a[first], b[first + per] = p.at[:-1], p.at[1:]
    slot = np.arange(len(t)) + td
    b[slot], a[slot + 1] = t + TRIGGER, t
    # dictionary: distinct phrases and the ranks of all their suffixes
    h = p.runs(a, b) ^ flat.mix((b - a).astype(np.uint64))
    _, rep, of = np.unique(h, return_index=True, return_inverse=True)
    lens = (b - a)[rep]
    base = np.cumsum(lens) - lens
    place = np.repeat(a[rep] - base, lens) + np.arange(int(lens.sum()))
    word = np.zeros(len(place), np.uint64)  # eight bytes at once start the doubling
    left = left_of(lens)
    for k in range(8):
        ok = left > k
        word[ok] |= p.raw[place[ok] + k].astype(np.uint64) << np.uint64(56 - 8 * k)
    in_dict = _doubled_words(word, left)
    # parse: the bodies as phrase ranks, and the ranks of its suffixes
    rank = in_dict[base][of]
    behind = np.append(doubled(rank, left_of(per + 1)), 0)
    behind[m] = 0
    # byte order: each start belongs to the phrase whose closing trigger it sees first
    s = np.concatenate([np.arange(x, y - length + 1) for x, y in zip(p.at[:-1].tolist(), p.at[1:].tolist())]) if len(bodies) else np.zeros(0, np.int64)
    body = np.searchsorted(p.at, s, side="right") - 1
    ph = np.searchsorted(t, s) + body  # triggers that start at or after s close its phrase
    is_last = ph == first[body] + per[body]
    alpha = in_dict[base[of[ph]] + s - a[ph]]
    return s, np.argsort(_packed(alpha, np.where(is_last, 0, behind[np.minimum(ph + 1, m)]))), p.runs, flat.Runs(flat.letters(33)[p.raw], 33)


def _doubled_words(word: np.ndarray, left: np.ndarray) -> np.ndarray:
    short = np.minimum(left, 8)  # a suffix that ends inside the eight bytes stands before its continuations
    return _double(_rank2(word, short), left, 8)


def _dense(x: np.ndarray) -> np.ndarray:
    order = np.argsort(x)
    y, out = x[order], np.empty(len(x), np.int64)
    out[order] = np.concatenate([[1], 1 + np.cumsum(y[1:] != y[:-1])]) if len(x) else 0
    return out


def _packed(major: np.ndarray, minor: np.ndarray) -> np.ndarray:
    return major.astype(np.uint64) << np.uint64(32) | minor.astype(np.uint64)


def _rank2(major: np.ndarray, minor: np.ndarray) -> np.ndarray:
    return _dense(_packed(_dense(major), minor))


def repeated_starts(length: int):
    """judge of annotate_bodies: for each piece a byte for each window start, 1 if its window stands elsewhere."""

    def ordered(bodies: list[bytes]) -> list[np.ndarray]:
        s, order, one, two = suffix_order(bodies, length)
        o = s[order]
        x, y = one(o, o + length), two(o, o + length)
        same = (x[1:] == x[:-1]) & (y[1:] == y[:-1])
        twin = np.empty(len(s), np.uint8)
        twin[order] = np.concatenate([[False], same]) | np.concatenate([same, [False]])
        return np.split(twin, np.cumsum([len(b) - length + 1 for b in bodies])[:-1])

    def run(bodies: list[bytes], many: np.ndarray, value: np.ndarray) -> list[np.ndarray]:
        notes: list = [None] * len(bodies)
        order = np.argsort(value, kind="stable").tolist()
        i = 0
        while i < len(order):
            j, size = i, 0
            while j < len(order) and (size < TOGETHER or value[order[j]] == value[order[j - 1]]):
                size += len(bodies[order[j]])
                j += 1
            for k, x in zip(order[i:j], ordered([bodies[k] for k in order[i:j]])):
                notes[k] = np.ones_like(x) if many[k] > 1 else x
            i = j
        return notes

    return run


def _counted(texts: DataFrame, length: int) -> DataFrame:
    """key, copies, n_bytes, sha and, where a window may stand elsewhere, text and phrase counts."""
    n = width(texts.sparkSession)

    def run(batches):
        for batch in batches:
            raw, notes = flat.as_bytes(batch.column(2)), batch.column(3).to_pylist()
            sha, text, counts = [], [], []
            for i, j in flat.parts(raw):
                p = Parse(raw[i:j], length)
                v = p.phrases()
                ends = np.cumsum(v.count)
                own = [exchange.deal(v.h[x:y], n, notes[i + d]) for d, (x, y) in enumerate(zip((ends - v.count).tolist(), ends.tolist()))]
                live = np.zeros(j - i, bool)
                live[p.pieces(np.concatenate(own))[3]] = True
                for d in range(j - i):
                    text.append(raw[i + d].decode() if live[d] else None)
                    counts.append(own[d].tobytes() if live[d] else None)
                    sha.append(None if live[d] else hashlib.sha256(raw[i + d]).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(list(map(len, raw)), pa.int64()), pa.array(sha, pa.string()), pa.array(text, pa.string()), pa.array(counts, pa.binary())], ["key", "copies", "n_bytes", "sha", "text", "counts"])

    noted = exchange.annotate(texts, phrase_values(length), how_often)
    return noted.select("key", "copies", "text", "notes").mapInArrow(run, "key binary, copies long, n_bytes long, sha string, text string, counts binary")


def _removed(live: DataFrame, length: int) -> DataFrame:
    """key, gone, spans, kept_sha: what goes from each text that may have repeats."""
    n, pieces, windows, cut = width(live.sparkSession), dealt_pieces(length), dealt_windows(length), marked(length)

    def run(batches):
        for batch in batches:
            raw, counts, one, two = flat.as_bytes(batch.column(1)), *(batch.column(k).to_pylist() for k in (2, 3, 4))
            gone, spans, sha = [], [], []
            for d, text in enumerate(raw):
                p, (i, j, value, _) = cut([text], [counts[d]])
                start = np.zeros(len(text), bool)
                own = np.flatnonzero(value > 0)
                own = own[np.argsort(exchange.bucket_of(flat.mix(value[own]), n), kind="stable")]
                note, at = np.frombuffer(one[d], np.uint8), 0
                for k in own.tolist():
                    start[i[k] : j[k]] = note[at : at + j[k] - i[k]]
                    at += j[k] - i[k]
                if at != len(note):
                    raise ValueError("notes and pieces differ")
                alone = np.flatnonzero(value == 0)
                if len(alone):
                    places = np.concatenate([np.arange(i[k], j[k]) for k in alone.tolist()])
                    start[places] = exchange.deal(flat.mix(p.runs(places, places + length)), n, two[d])
                out = covered(np.flatnonzero(start), length, len(text))
                gone.append(int(out.sum()))
                spans.append(int(np.diff(out.astype(np.int8), prepend=0).clip(0).sum()))
                sha.append(hashlib.sha256(p.raw[~out].tobytes()).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(gone, pa.int64()), pa.array(spans, pa.int64()), pa.array(sha, pa.string())], ["key", "gone", "spans", "kept_sha"])

    first = exchange.annotate_bodies(live, pieces, repeated_starts(length), extra="counts").withColumnRenamed("notes", "one")
    both = exchange.annotate(first, windows, twice, wide=True, extra="counts")
    return both.select("key", "text", "counts", "one", "notes").mapInArrow(run, "key binary, gone long, spans long, kept_sha string")


def remove_repeated_bytes(docs: DataFrame, length: int = 400, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256: bytes in a string of `length` bytes that also starts elsewhere go."""
    counted = durable(_counted(exchange.distinct_texts(docs, doc_id, text), length), "phrases")
    live = counted.where("counts is not null").select("key", F.lit(None).cast("long").alias("rep"), "text", "counts")
    by_text = counted.select("key", "copies", "n_bytes", "sha").join(_removed(live, length), "key", "left")
    out = docs.select(F.col(doc_id).alias("doc_id"), exchange.text_key(text).alias("key")).join(by_text, "key", "left")
    whole = (F.col("copies") > 1) & (F.col("n_bytes") >= length)
    return out.select(
        "doc_id",
        F.coalesce("n_bytes", F.lit(0)).cast("long").alias("n_bytes"),
        F.when(whole, F.col("n_bytes")).otherwise(F.coalesce("gone", F.lit(0))).cast("long").alias("n_removed"),
        F.when(whole, F.lit(1)).otherwise(F.coalesce("spans", F.lit(0))).cast("long").alias("n_spans"),
        F.when(whole, F.lit(NOTHING)).otherwise(F.coalesce("kept_sha", "sha", F.lit(NOTHING))).alias("kept_sha256"),
    )


def op8(spark, sf_dir: str) -> DataFrame:
    return remove_repeated_bytes(table(spark, sf_dir, "documents"), 400)
