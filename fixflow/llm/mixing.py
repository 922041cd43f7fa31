"""Language-model scoring by online logistic context mixing of bit predictors.

A text is its tokens: lower-cased words and one end. Each token is a string of binary decisions. The first: is it known after the word
before it, which means that the corpus has this pair of tokens? Several hashed contexts predict that bit: how often the word before was seen together with the length of the
run of known tokens behind it; the word before; the two words before; the last of the ``TOP`` most frequent words (which tells the language of the passage).
Their log-odds are mixed by weights that a gate selects (run, how often the two words were seen), and the mixed probability is refined by
an adaptive table of outcomes by gate and log-odds. Tables, weights and refinement are learned online over the text: each piece of text is predicted
by what the pieces before it have left, with every token's own pair left out of its count.
A known token is then coded by its share of the pairs of the word before (a word beyond the ``HEAD`` most frequent tokens counts as often as the last of these).
Any other token is coded from scratch: whether it is one of the head; if so, the digits of its frequency rank, predicted from the digits before them
alone and together with the frequent word; if not (or if it was seen once only), the bits of its bytes and of a closing space, predicted in hashed contexts of the last one, two, three and four
bytes; these are mixed, gated and refined alike. Known tokens could be coded both ways, so the probabilities of all texts add up to
less than one, never more.

What is gathered grows with the corpus: token counts and the counts of all pairs are kept whole (pairs are counted by 37-bit or longer hashes, see
``exchange``, and come back to the texts as a byte: counts over 127 are rounded down to quarters of a power of two). Tables of hashed contexts have a fixed size and are summed
over tasks by block, without a limit on a count;
the weights that tasks learn are averaged by the tokens they saw. Only tables of fixed size are collected or broadcast. Exact token counts reach the documents by
the broadcast head and, for all other tokens, by a join.

Nulls: a null text has no words and one end. A null id is trained on. Rows that share a text share its score. Words of any length are spelled whole. With no
training rows all counts are 0 and every decision has even odds. Extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import exchange, flat
from .common import durable, release, table, width
from .langid import fold

BITS = (16, 20, 21, 22)  # log2 of each predictor's slots
BASE = np.concatenate([[0], np.cumsum([1 << b for b in BITS])])
SLOTS = int(BASE[-1])
BLOCK = 1 << 14
FULL = 1 << 31
SMALL = 1 << 19  # bytes of text whose known bits are predicted at once
HEAD, TOP = 1 << 17, 32
GATES = 8 * 4 * 8 * 4  # bit place, bytes read, how often the last three bytes were seen, and the last four
RANK_GATES = 18 * 8  # digit place, how often it was seen after this frequent word
GATE_BLOCK = 32  # gates whose sums over tasks are added up together
STEPS = 32
CELL = np.uint64(44)  # a head word is looked for among those with the same bits above these
PRIOR = 0.4
END = b"\n"
ENDS, BEGINS = np.uint64(0xE703C2A9D1B5F68D), np.uint64(0x5B1D9E37A46C80F3)  # hashes of the end, and of the place before the first word
KNOWN_BITS = (12, 16, 18, 10)  # log2 of the slots of each predictor of the known bit
KNOWN_BASE = np.concatenate([[0], np.cumsum([1 << b for b in KNOWN_BITS])])
KNOWN_GATES = 8 * 4  # run of known tokens, how often the two words before were seen


class Spelled:
    """Bits of spelled words in a flat array: slot of each predictor, outcome, gate place, word of each byte."""

    def __init__(self, words: list[bytes]):
        raw = np.frombuffer(b"".join([w + b" " for w in words]), np.uint8)
        lens = np.fromiter(map(len, words), np.int64, len(words)) + 1
        at = np.cumsum(lens) - lens
        self.word = np.repeat(np.arange(len(words)), lens)
        i = np.arange(len(raw))
        pos = i - at[self.word]
        before = [np.where(pos >= k, raw[np.maximum(i - k, 0)].astype(np.uint64) + np.uint64(1), np.uint64(0)) for k in (1, 2, 3, 4)]
        two = before[0] | before[1] << np.uint64(9)
        three = two | before[2] << np.uint64(18)
        contexts = [before[0], two, three, three | before[3] << np.uint64(27)]
        bit = np.arange(8)
        node = ((1 << bit)[None] | (raw[:, None].astype(np.int64) >> (8 - bit)[None])).astype(np.uint64)
        self.y = ((raw[:, None] >> (7 - bit)[None]) & 1).astype(bool)
        step = node.astype(np.uint32) * np.uint32(0x9E3779B9)
        self.slot = []
        for k, (c, b) in enumerate(zip(contexts, BITS)):
            h = (flat.mix(c + np.uint64(k)).astype(np.uint32)[:, None] + step) * np.uint32(0xD35A2D97)
            self.slot.append(((h >> np.uint32(32 - b)) + np.uint32(BASE[k])).astype(np.int64))
        self.place = (np.minimum(pos, 3)[:, None] * 8 + bit[None]) * 32


def odds(n: np.ndarray, y: np.ndarray | None = None) -> np.ndarray:
    """Log-odds of counts [.., 2]; y: leave out one occurrence of it."""
    zero, one = n[..., 0].astype(np.float32), n[..., 1].astype(np.float32)
    if y is not None:
        zero, one = zero - ~y, one - y
        zero, one = np.maximum(zero, 0), np.maximum(one, 0)
    return np.log((one + PRIOR) / (zero + PRIOR))


_LOGS = np.log(np.concatenate([[0], np.arange(1 << 16)]) + PRIOR).astype(np.float32)  # of a count at the place after it


def small_odds(zero: np.ndarray, one: np.ndarray, y: np.ndarray) -> np.ndarray:
    """As odds for counts of 16 bits, one occurrence of y left out."""
    return _LOGS.take(one + (1 - y)) - _LOGS.take(zero + y)


def squash(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -12, 12)))


def digits(n: np.ndarray) -> np.ndarray:
    """0 to 7: how often a slot was seen, in steps of about four times."""
    return np.minimum(7, np.ceil(np.log2(n + 1.0) / 1.75)).astype(np.uint8)


_DIGITS = digits(np.arange(1 << 17))


def gate(place: np.ndarray, three: np.ndarray, four: np.ndarray) -> np.ndarray:
    return place + three.astype(np.int64) * 4 + np.minimum(four, 6) // 2


def bucket(x: np.ndarray) -> np.ndarray:
    return np.clip((x + 8) * 2, 0, STEPS - 1).astype(np.int64)


class Model:
    """Speller: odds of every slot, mixing weights [gate, predictor + 1] and the refining table [gate, step] of probabilities."""

    def __init__(self, logit: np.ndarray, seen: np.ndarray, weights: np.ndarray, refine: np.ndarray):
        self.logit, self.seen, self.weights, self.refine = logit, seen, np.ascontiguousarray(weights.T), refine

    def score(self, words: list[bytes]) -> np.ndarray:
        """log2 probability of each spelled word."""
        out = np.zeros(len(words))
        for i, j in chunks(words):
            s = Spelled(words[i:j])
            g = gate(s.place, self.seen.take(s.slot[2]), self.seen.take(s.slot[3]))
            mixed = self.weights[-1].take(g)
            for own, slot in zip(self.weights, s.slot):
                mixed += own.take(g) * self.logit.take(slot).astype(np.float32)
            p = (squash(mixed) + self.refine.take(g * STEPS + bucket(mixed))) / 2
            bits = np.log2(np.where(s.y, p, 1 - p)).sum(1)
            out[i:j] = np.bincount(s.word, bits, minlength=j - i)
        return out


def chunks(words: list[bytes], most: int = 8_000):
    """Index ranges of words with about `most` bytes each."""
    return flat.parts(words, most)


class Online:
    """Learns mixing weights and the refining table, batch after batch."""

    def __init__(self, inputs: int, gates: int, guess: list[float]):
        n = inputs + 1
        self.w = np.tile(np.array([*guess, 0.0]), (gates, 1))
        self.h = np.tile(np.eye(n) * 20.0, (gates, 1, 1))
        self.seen = np.zeros((gates, STEPS, 2))
        self.weight = np.zeros(gates)

    def learn(self, x: np.ndarray, y: np.ndarray, g: np.ndarray, times: np.ndarray) -> None:
        """x: log-odds [event, predictor] and the constant; y: outcome; g: gate; times: weight of each event."""
        order = np.argsort(g.astype(np.int16), kind="stable")  # gates are few, so this is a radix sort
        n, z, y, times = x.shape[1], x.take(order, axis=0).astype(np.float64), y.take(order), times.take(order)
        per = np.bincount(g, minlength=len(self.weight))
        own = np.flatnonzero(per)
        ends = np.cumsum(per[own]).tolist()
        mixed = np.einsum("ij,ij->i", np.repeat(self.w[own], per[own], axis=0), z)
        p, g = squash(mixed), np.repeat(own, per[own])
        self.seen += np.bincount((g * STEPS + bucket(mixed)) * 2 + y, times, minlength=self.seen.size).reshape(self.seen.shape)
        self.weight += np.bincount(g, times, minlength=len(self.weight))
        right = np.empty((len(z), n + 1))  # curvature and slope in one product
        np.multiply(z, (p * (1 - p) * times)[:, None], out=right[:, :n])
        right[:, n] = (y - p) * times
        sums = np.empty((len(own), n, n + 1))
        for k, (i, j) in enumerate(zip([0, *ends], ends)):
            np.matmul(z[i:j].T, right[i:j], out=sums[k])
        self.h[own] += sums[:, :, :n]
        self.w[own] += np.linalg.solve(self.h[own], sums[:, :, n:])[..., 0]

    def refined(self) -> np.ndarray:
        centre = squash((np.arange(STEPS) + 0.5) / 2 - 8)
        return np.clip((self.seen[..., 1] + 20 * centre) / (self.seen.sum(-1) + 20), 1e-6, 1 - 1e-6)


def speller() -> Online:
    return Online(len(BITS), GATES, [0.0, 0.2, 0.4, 0.4])


def learn_words(own: Online, counts: np.ndarray, words: list[bytes], times: np.ndarray) -> None:
    """counts: 16 bits each."""
    s = Spelled(words)
    y, both, seen = s.y.ravel(), counts.reshape(-1).view("<u4"), []
    x = np.empty((y.size, len(BITS) + 1), np.float32)
    x[:, -1] = 0.3
    for k, slot in enumerate(s.slot):
        pair = both.take(slot.ravel()).astype(np.int64)
        zero, one = pair & 0xFFFF, pair >> 16
        x[:, k] = small_odds(zero, one, y)
        if k >= 2:
            seen.append(_DIGITS.take(np.maximum(zero + one - 1, 0)))
    g = gate(s.place.ravel(), *seen)
    own.learn(x, y, g, np.repeat(times[s.word], 8))


def rank_bits() -> int:
    return HEAD.bit_length() - 1


def head_odds(counts: np.ndarray) -> np.ndarray:
    """log2 probability [kind, rank or HEAD for none of them] from counts of the same shape.

    The decisions are nodes of a binary tree over ranks (under `is it in the head`), so counts of (kind, node) hold all there is to learn from."""
    kinds, bits = len(counts), rank_bits()
    own = Online(2, RANK_GATES, [0.1, 0.9])

    def nodes(c: np.ndarray):
        """Counts of 0 and 1 at every decision: first the escape, then the digits from the top."""
        c = c.astype(np.int64)
        yield np.array([[c[:HEAD].sum(), c[HEAD]]])
        for b in range(bits):
            yield c[:HEAD].reshape(1 << b, 2, -1).sum(2)

    whole = list(nodes(counts.sum(0, dtype=np.int64)))

    def inputs(k: int, b: int, n: np.ndarray, y: np.ndarray | None):
        x = np.stack([odds(whole[b], y), odds(n, y), np.full(len(n), 0.3, np.float32)], 1)
        return x, b * 8 + digits(np.maximum(n.sum(1) - (y is not None), 0)).astype(np.int64)

    for k in range(kinds):
        for b, n in enumerate(nodes(counts[k])):
            for outcome in (False, True):
                live = n[:, int(outcome)] > 0
                if live.any():
                    x, g = inputs(k, b, n, np.full(len(n), outcome))
                    own.learn(x[live], np.full(int(live.sum()), outcome), g[live], n[live, int(outcome)].astype(np.float64))
    refine = own.refined()
    out = np.zeros((kinds, HEAD + 1), np.float32)
    for k in range(kinds):
        for b, n in enumerate(nodes(counts[k])):
            x, g = inputs(k, b, n, None)
            mixed = (own.w[g] * x).sum(1)
            p = (squash(mixed) + refine[g, bucket(mixed)]) / 2
            both = np.log2(np.stack([1 - p, p], 1))
            if b == 0:
                out[k, :HEAD], out[k, HEAD] = both[0, 0], both[0, 1]
            else:
                out[k, :HEAD] += np.repeat(both.ravel(), HEAD >> b)
    return out


class Head:
    """Ranks of the most frequent tokens by hash of the word."""

    def __init__(self, words: list[bytes]):
        self.end = words.index(END) if END in words else -1
        known = flat.Words([b"" if w == END else w for w in words])
        rank = np.array([r for r, w in enumerate(words) if w != END], np.int64)
        h = known.hashes(43)
        order = np.argsort(h)
        self.hash, self.rank, self.cell = h[order], rank[order], None

    def ranks(self, h: np.ndarray) -> np.ndarray:
        """HEAD for words that aren't in the head."""
        if not len(self.hash):
            return np.full(len(h), HEAD)
        if self.cell is None:  # made where it is used, not sent
            per = np.bincount((self.hash >> CELL).astype(np.int64), minlength=1 << (64 - int(CELL)))
            self.cell, self.most = (np.cumsum(per) - per).astype(np.int32), int(per.max())
            self.padded, self.ranked = np.concatenate([self.hash, self.hash[:1].repeat(self.most)]), np.concatenate([self.rank, self.rank[:1].repeat(self.most)])
        at = self.cell.take((h >> CELL).astype(np.int64))
        hit = self.padded.take(at) == h
        out = np.where(hit, self.ranked.take(at), HEAD)
        left = np.flatnonzero(~hit)
        for k in range(1, self.most):  # words that share a cell stand side by side
            own = at.take(left) + k
            hit = self.padded.take(own) == h.take(left)
            out[left[hit]] = self.ranked.take(own[hit])
            left = left[~hit]
        return out


def _pieces(raw: list[bytes], head: Head | None, most: int = flat.PIECE):
    """Texts in pieces: words, their hashes, ranks and kinds (one more than the rank of the last frequent word before, 0: none), and the kind before each end."""
    for i, j in flat.parts(raw, most):
        w = flat.Words(raw[i:j], fold=True)
        h = w.hashes(43)
        if head is None:
            yield i, j, w, h, None, None, None
            continue
        rank = head.ranks(h)
        at = np.arange(len(h))
        last = np.maximum.accumulate(np.where(rank < TOP, at, -1)) if len(h) else at
        begin = w.first[w.doc]
        before = np.concatenate([[-1], last[:-1]]) if len(h) else last
        kind = np.where(before >= begin, rank[np.maximum(before, 0)] + 1, 0) if len(h) else at
        end_kind = np.zeros(j - i, np.int64)
        has = np.flatnonzero(w.count > 0)
        final = last[w.first[1:][has] - 1]
        end_kind[has] = np.where(final >= w.first[:-1][has], rank[np.maximum(final, 0)] + 1, 0) if len(has) else 0
        yield i, j, w, h, rank, kind, end_kind


def count_tokens(train: DataFrame, text: str) -> DataFrame:
    """word, n over all tokens; the end is the word of one line feed."""

    def rows(seen: dict[bytes, int]):
        return pa.RecordBatch.from_arrays([pa.array(list(seen), pa.binary()), pa.array(list(seen.values()), pa.int64())], ["word", "n"])

    def run(batches):
        seen: dict[bytes, int] = {}
        for batch in batches:
            for i, j, w, h, *_ in _pieces(flat.as_bytes(batch.column(0)), None):
                order = np.argsort(h)
                ordered = h.take(order)
                cut = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]])) if len(h) else order
                first, n = order.take(cut), np.diff(np.append(cut, len(h)))
                text = w.raw.tobytes()
                for x, y, c in zip(w.start[first].tolist(), w.end[first].tolist(), n.tolist()):
                    word = text[x:y]
                    seen[word] = seen.get(word, 0) + c
                seen[END] = seen.get(END, 0) + j - i
                if len(seen) > 250_000:
                    yield rows(seen)
                    seen = {}
        if seen:
            yield rows(seen)

    return train.select(F.col(text)).mapInArrow(run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


def most_frequent(words: DataFrame, most: int) -> DataFrame:
    """The end and the most frequent of the words seen more than once, `most` rows at most; of equally frequent ones those of the smallest hash.

    Two histograms of bounded size narrow the words down, so that the sort meets little more than `most` rows in all, however many partitions there are."""
    many = words.where((F.col("n") > 1) & (F.col("word") != F.lit(END)))
    step = F.when(F.col("n") < 1024, F.col("n")).otherwise((1024 + 64 * (F.log2(F.col("n").cast("double")) - 10)).cast("long"))
    tie = F.pmod(F.xxhash64("word"), F.lit(1 << 14))

    def cut(rows: DataFrame, by, falling: bool, room: int):
        """Last value of `by` that is needed to fill the room, and what is taken before it."""
        taken = 0
        for value, n in sorted(((r.at, r.n) for r in rows.groupBy(by.cast("long").alias("at")).agg(F.count("*").alias("n")).collect()), reverse=falling):
            if taken + n >= room:
                return value, taken
            taken += n
        return None, taken

    last, taken = cut(many, step, True, most - 1)
    if last is not None:
        upper, _ = cut(many.where(step == last), tie, False, most - 1 - taken)
        many = many.where((step > last) | ((step == last) & (tie <= upper)))
    rest = many.orderBy(F.desc(step), tie, F.xxhash64("word"), "word").limit(most - 1)
    return words.where(F.col("word") == F.lit(END)).unionByName(rest)


def _blocks(total: np.ndarray):
    rows = total.reshape(-1, 2 * BLOCK)
    for b in np.flatnonzero(rows.any(1)).tolist():
        yield pa.RecordBatch.from_pydict({"block": [b], "counts": [rows[b].tobytes()]}, pa.schema([("block", pa.int32()), ("counts", pa.binary())]))


def _summed(parts: DataFrame, size: int) -> np.ndarray:
    """Flat counts of a fixed size, added up over tasks by block."""

    def add(pdf):
        import pandas as pd

        total = np.zeros(2 * BLOCK, np.int64)
        for x in pdf["counts"]:
            total += np.frombuffer(x, np.uint32)
        return pd.DataFrame({"block": pdf["block"].iloc[:1], "counts": [total.astype(np.float32).tobytes()]})

    out = np.zeros((-(-size // (2 * BLOCK)), 2 * BLOCK), np.float32)
    for r in parts.groupBy("block").applyInPandas(add, "block int, counts binary").toLocalIterator():  # a table of fixed size
        out[r.block] = np.frombuffer(r.counts, np.float32)
    return out.ravel()[:size]


def count_ranks(train: DataFrame, text: str, head: Head) -> np.ndarray:
    """[kind, rank] counts over all tokens."""
    shared, size = train.sparkSession.sparkContext.broadcast(head), (TOP + 1) * (HEAD + 1)

    def run(batches):
        total, held = np.zeros(-(-size // (2 * BLOCK)) * 2 * BLOCK, np.uint32), 0
        for batch in batches:
            for i, j, w, h, rank, kind, end_kind in _pieces(flat.as_bytes(batch.column(0)), shared.value):
                cell = np.concatenate([kind * (HEAD + 1) + rank, end_kind * (HEAD + 1) + shared.value.end])
                held += len(cell)
                if held >= FULL:  # before a counter could wrap
                    yield from _blocks(total)
                    total[:], held = 0, len(cell)
                at, n = np.unique(cell, return_counts=True)
                total[at] += n.astype(np.uint32)
        yield from _blocks(total)

    return _summed(train.select(F.col(text)).mapInArrow(run, "block int, counts binary"), size).reshape(TOP + 1, HEAD + 1)


def train_speller(rare: DataFrame, distinct: int) -> Model:
    """rare: word, n of the tokens to learn from."""
    tasks = max(1, min(4096, -(-distinct // 500_000)))
    tokens = durable(rare.select("word", "n").repartition(tasks, "word"), "tokens")
    tokens = tokens.repartition(tasks, "word").sortWithinPartitions(F.xxhash64("word"), "word")  # the same tasks and order whoever runs them

    def count(batches):
        total, held = np.zeros(SLOTS * 2, np.uint32), 0
        for batch in batches:
            words, n = batch.column(0).to_pylist(), batch.column(1).to_numpy()
            for i, j in chunks(words, 120_000):
                s = Spelled(words[i:j])
                t = np.repeat(n[i:j][s.word], 8)
                parts = int(t.sum()) // FULL + 1
                for q in range(parts):
                    part = t // parts + (q < t % parts)
                    held += int(part.sum())
                    if held >= FULL:  # before a counter could wrap
                        yield from _blocks(total)
                        total[:], held = 0, int(part.sum())
                    for slot in s.slot:
                        np.add.at(total, slot.ravel() * 2 + s.y.ravel(), part.astype(np.uint32))
        yield from _blocks(total)

    counts = _summed(tokens.mapInArrow(count, "block int, counts binary"), 2 * SLOTS).reshape(SLOTS, 2)
    small = np.empty((SLOTS, 2), np.uint16)
    for i in range(0, SLOTS, 1 << 18):  # in parts, for the driver's memory
        part = counts[i : i + (1 << 18)]
        top = np.maximum(part.max(1, keepdims=True), 1)
        small[i : i + (1 << 18)] = np.where(top > 65535, np.ceil(part * (65535 / top)), part)
    counts = small
    shared = rare.sparkSession.sparkContext.broadcast(counts)

    def learn(batches):
        own = speller()
        for batch in batches:
            words, n = batch.column(0).to_pylist(), batch.column(1).to_numpy()
            for i, j in chunks(words, 60_000):
                learn_words(own, shared.value, words[i:j], n[i:j].astype(np.float64))
        if own.weight.any():
            all_ = np.concatenate([own.w * own.weight[:, None], own.weight[:, None], own.seen.reshape(GATES, -1)], 1)
            for b, part in enumerate(np.split(all_, GATES // GATE_BLOCK)):
                yield pa.RecordBatch.from_pydict({"block": [b], "sums": [part.tobytes()]}, pa.schema([("block", pa.int32()), ("sums", pa.binary())]))

    mean = speller()
    guess, n = mean.w.copy(), len(BITS) + 1

    def add(pdf):
        import pandas as pd

        total = sum((np.frombuffer(x, np.float64) for x in sorted(pdf["sums"])), 0.0)  # in a fixed order, so that a task run again gives the same
        return pd.DataFrame({"block": pdf["block"].iloc[:1], "sums": [total.tobytes()]})

    for r in tokens.mapInArrow(learn, "block int, sums binary").groupBy("block").applyInPandas(add, "block int, sums binary").toLocalIterator():  # a table of fixed size
        own, rows = np.frombuffer(r.sums, np.float64).reshape(GATE_BLOCK, -1), slice(r.block * GATE_BLOCK, (r.block + 1) * GATE_BLOCK)
        mean.w[rows], mean.weight[rows], mean.seen[rows] = own[:, :n], own[:, n], own[:, n + 1 :].reshape(GATE_BLOCK, STEPS, 2)
    w = np.where(mean.weight[:, None] > 0, mean.w / np.maximum(mean.weight, 1e-9)[:, None], guess)
    w[:, -1] *= 0.3  # the constant input
    shared.unpersist()
    logit, seen = np.empty(SLOTS, np.float16), np.empty(SLOTS, np.uint8)
    for i in range(0, SLOTS, 1 << 18):
        part = counts[i : i + (1 << 18)]
        logit[i : i + (1 << 18)], seen[i : i + (1 << 18)] = odds(part), digits(part.sum(1, dtype=np.int64))
    return Model(logit, seen, w.astype(np.float32), mean.refined().astype(np.float32))


class Stream:
    """The tokens of a piece of texts, each text's end among them: hash, the hashes of the two tokens before, kind, begin of the text."""

    def __init__(self, w: flat.Words, h: np.ndarray, kind: np.ndarray | None = None, end_kind: np.ndarray | None = None):
        m = len(w.count)
        self.at = np.arange(len(h)) + w.doc  # of the words
        self.ends = w.first[1:] + np.arange(m)
        self.doc = np.repeat(np.arange(m), w.count + 1)
        self.first = np.concatenate([[0], self.ends[:-1] + 1]) if m else np.zeros(0, np.int64)
        self.h = np.empty(len(h) + m, np.uint64)
        self.h[self.at], self.h[self.ends] = h, ENDS
        self.one, self.two = self.before(self.h, BEGINS), self.before(self.before(self.h, BEGINS), BEGINS)
        self.kind = None
        if kind is not None:
            self.kind = np.empty(len(self.h), np.int64)
            self.kind[self.at], self.kind[self.ends] = kind, end_kind

    def before(self, x: np.ndarray, none) -> np.ndarray:
        out = np.roll(x, 1)
        out[self.first] = none
        return out

    def pairs(self) -> np.ndarray:
        return flat.mix(self.one * np.uint64(0x9E3779B97F4A7C15) + self.h)

    def runs(self, known: np.ndarray) -> np.ndarray:
        """0 to 7: how many tokens before each one are known without a gap, in powers of two."""
        at = np.arange(len(known))
        last = np.maximum(np.maximum.accumulate(np.where(known, -1, at)) if len(at) else at, self.first[self.doc] - 1)
        run = np.where(known, at - last, 0)
        return np.minimum(7, np.ceil(np.log2(self.before(run, 0) + 1.0))).astype(np.int64)

    def contexts(self, total: np.ndarray, run: np.ndarray) -> list[np.ndarray]:
        """Slots of the predictors of the known bit."""
        level = np.minimum(31, np.log2(total + 1.0) * 2).astype(np.int64)
        hashed = [flat.mix(self.one ^ np.uint64(0x51)), flat.mix(self.one * np.uint64(3) + flat.mix(self.two))]
        by_word = [(x >> np.uint64(64 - b)).astype(np.int64) for x, b in zip(hashed, KNOWN_BITS[1:3])]
        return [level * 8 + run + KNOWN_BASE[0], by_word[0] + KNOWN_BASE[1], by_word[1] + KNOWN_BASE[2], np.minimum(self.kind, 63) * 8 + run + KNOWN_BASE[3]]


def pair_values(texts: list[bytes], _=None) -> exchange.Values:
    w = flat.Words(texts, fold=True)
    return exchange.Values(Stream(w, w.hashes(43)).pairs(), w.count + 1)


def pair_counts(values: np.ndarray, flags, ranks: np.ndarray) -> np.ndarray:
    """How often each value stands in the training texts (a rank is the number of a text's training copies), as a byte."""
    order, s = exchange.sorted_low(values["low"])
    cut = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]])) if len(s) else np.zeros(0, np.int64)
    if not len(cut):
        return np.zeros(0, np.uint8)
    n = np.add.reduceat(ranks["rep"].take(order), cut)
    note = np.where(n < 128, n, 128 + np.floor(4 * np.log2(np.maximum(n, 128) / 128)))
    out = np.empty(len(s), np.uint8)
    out[order] = np.repeat(note.astype(np.uint8), np.diff(np.append(cut, len(s))))
    return out


COUNT_OF = np.where(np.arange(256) < 128, np.arange(256), np.floor(128 * 2.0 ** ((np.arange(256) - 128) / 4)))


def totals(stream: Stream, head_times: np.ndarray, rank: np.ndarray, documents: int) -> np.ndarray:
    """How often the token before each one was seen; of words beyond the head, at most how often."""
    own = np.empty(len(stream.h))
    own[stream.at], own[stream.ends] = head_times[rank], 0
    return stream.before(own, documents)


def _known_odds(counts: list[np.ndarray]) -> np.ndarray:
    x = [np.log((c[:, 1] + PRIOR) / (c[:, 0] + PRIOR)) for c in counts]
    return np.stack([*x, np.full(len(x[0]), 0.3)], 1)


def known_gate(run: np.ndarray, seen: np.ndarray) -> np.ndarray:
    return run * 4 + np.minimum(3, np.log2(seen + 1.0)).astype(np.int64)


class Known:
    """Predictors of the known bit: outcome counts of every slot, mixing weights and refining table."""

    def __init__(self, counts: np.ndarray, weights: np.ndarray, refine: np.ndarray):
        self.counts, self.weights, self.refine = counts, weights.astype(np.float32), refine.astype(np.float32)
        c = counts.astype(np.float64)
        self.odds, self.seen = np.log((c[:, 1] + PRIOR) / (c[:, 0] + PRIOR)).astype(np.float32), c.sum(1).astype(np.float32)

    def probability(self, stream: Stream, total: np.ndarray, known: np.ndarray) -> np.ndarray:
        """That each token is known."""
        run = stream.runs(known)
        slots = stream.contexts(total, run)
        g = known_gate(run, self.seen.take(slots[2]))
        mixed = self.weights[:, -1].take(g) * np.float32(0.3)
        for own, s in zip(self.weights.T, slots):
            mixed += own.take(g) * self.odds.take(s)
        return np.clip((squash(mixed) + self.refine.take(g * STEPS + bucket(mixed))) / 2, 1e-6, 1 - 1e-6).astype(np.float64)


def known_mixer() -> Online:
    return Online(len(KNOWN_BITS), KNOWN_GATES, [0.5, 0.2, 0.1, 0.2])


def growing(texts: list[bytes], read: int):
    """Index ranges of texts in pieces that grow with what was read, so that the first pieces are predicted early."""
    first = size = 0
    for i, t in enumerate(texts):
        size += len(t)
        if size >= min(SMALL, max(1 << 15, (read + size) // 8)):
            yield first, i + 1
            read, first, size = read + size, i + 1, 0
    if first < len(texts):
        yield first, len(texts)


def learn_known(noted: DataFrame, head, head_times: np.ndarray, documents: int) -> Known:
    """Reads all training texts in order, once; noted: text, notes, times (training copies)."""
    n, size = width(noted.sparkSession), int(KNOWN_BASE[-1])
    shared = noted.sparkSession.sparkContext.broadcast((head, head_times))

    def learn(batches):
        head, head_times = shared.value
        own, counts, read = known_mixer(), np.zeros((size, 2)), 0
        pairs = counts.reshape(-1).view(np.complex128)  # the same memory: both counts of a slot in one look
        for batch in batches:
            raw, notes, copies = flat.as_bytes(batch.column(0)), batch.column(1).to_pylist(), batch.column(2).to_numpy()
            for first, last in growing(raw, read):
                for i, j, w, h, rank, kind, end_kind in _pieces(raw[first:last], head, SMALL):
                    i, j = first + i, first + j
                    t = Stream(w, h, kind, end_kind)
                    c = COUNT_OF[_dealt(t, notes[i:j], n)] - 1  # without the token itself
                    total = np.maximum(totals(t, head_times, rank, documents) - 1, 0)
                    known = c > 0
                    run = t.runs(known)
                    live = np.flatnonzero(total > 0)  # nothing can be known after what was never seen
                    if not len(live):
                        continue
                    slots = [s[live] for s in t.contexts(total, run)]
                    y, times = known[live], copies[i:j][t.doc[live]].astype(np.float64)
                    seen = [pairs.take(s).view(np.float64).reshape(-1, 2) for s in slots]
                    own.learn(_known_odds(seen), y, known_gate(run[live], seen[2].sum(1)), times)
                    for s, low, high in zip(slots, KNOWN_BASE, KNOWN_BASE[1:]):
                        counts[low:high] += np.bincount((s - low) * 2 + y, times, minlength=2 * (high - low)).reshape(-1, 2)
            read += sum(map(len, raw))
        if own.weight.any():
            sums = np.concatenate([own.w * own.weight[:, None], own.weight[:, None], own.seen.reshape(KNOWN_GATES, -1)], 1)
            flat_ = np.concatenate([sums.ravel(), counts.ravel()])
            for b, at in enumerate(range(0, len(flat_), 2 * BLOCK)):
                yield pa.RecordBatch.from_pydict({"block": [b], "sums": [flat_[at : at + 2 * BLOCK].astype(np.float32 if at > sums.size else np.float64).tobytes()]}, pa.schema([("block", pa.int32()), ("sums", pa.binary())]))

    wide = KNOWN_GATES * (len(KNOWN_BITS) + 2 + 2 * STEPS)
    kind_of = lambda b: np.float32 if b * 2 * BLOCK > wide else np.float64

    def add(pdf):
        import pandas as pd

        b = int(pdf["block"].iloc[0])
        total = sum((np.frombuffer(x, kind_of(b)).astype(np.float64) for x in sorted(pdf["sums"])), 0.0)  # in a fixed order
        return pd.DataFrame({"block": [b], "sums": [total.tobytes()]})

    out = np.zeros(wide + 2 * size)
    rows = noted.where("times > 0").select("text", "notes", "times").mapInArrow(learn, "block int, sums binary")
    for r in rows.groupBy("block").applyInPandas(add, "block int, sums binary").toLocalIterator():  # a table of fixed size
        part = np.frombuffer(r.sums, np.float64)
        out[r.block * 2 * BLOCK : r.block * 2 * BLOCK + len(part)] = part
    shared.unpersist()
    mean, sums = known_mixer(), out[:wide].reshape(KNOWN_GATES, -1)
    k = len(KNOWN_BITS) + 1
    weight = sums[:, k]
    w = np.where(weight[:, None] > 0, sums[:, :k] / np.maximum(weight, 1e-9)[:, None], mean.w)
    mean.seen = sums[:, k + 1 :].reshape(KNOWN_GATES, STEPS, 2)
    return Known(out[wide:].reshape(size, 2).astype(np.float32), w, mean.refined())


def _dealt(t: Stream, notes: list[bytes], n: int) -> np.ndarray:
    """The notes of a piece's tokens in the order of the text."""
    if not np.array_equal(np.fromiter(map(len, notes), np.int64, len(notes)), t.ends + 1 - t.first):
        raise ValueError("notes and tokens differ")
    order = np.argsort(exchange.bucket_of(t.pairs(), n), kind="stable")
    doc = t.doc.take(order)
    order = order.take(np.argsort(doc.astype(np.uint16) if len(notes) <= 1 << 16 else doc, kind="stable"))  # both are radix sorts
    out = np.empty(len(t.h), np.uint8)
    out[order] = np.frombuffer(b"".join(notes), np.uint8)
    return out


def score_texts(docs: DataFrame, train: DataFrame | Column, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """docs' id with n_tokens, n_known, train_tokens, base_score, score (log10) and bits_per_byte.

    train: the rows to learn from, or the condition on docs that tells them, which reads docs' texts once."""
    spark = docs.sparkSession
    full = F.coalesce(F.col(text), F.lit("")).alias("text")
    if isinstance(train, Column):
        both = docs.select(full, train.cast("long").alias("times"), F.lit(1).cast("long").alias("asked"))
        train = docs.where(train)
    else:
        both = docs.select(full, F.lit(0).cast("long").alias("times"), F.lit(1).cast("long").alias("asked"))
        both = both.unionByName(train.select(full, F.lit(1).cast("long").alias("times"), F.lit(0).cast("long").alias("asked")))
    words = durable(count_tokens(train, text), "counted")
    total = words.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count("*").alias("v")).first()
    n, v = int(total.n), int(total.v)
    # tokens seen once are spelled: they stand for those not seen at all
    most = sorted((-r.n, bytes(r.word)) for r in most_frequent(words, HEAD).toLocalIterator())  # HEAD rows at most
    head = Head([w for _, w in most] if most else [END])
    times = np.zeros(HEAD + 1)
    times[: len(most)] = [-n for n, _ in most]
    documents = int(times[head.end]) if head.end >= 0 else 0
    least = max(1.0, 1.02 * times[len(most) - 1]) if len(most) >= HEAD else 1.0  # no word beyond the head is seen more often
    head_times = np.where(np.arange(HEAD + 1) < HEAD, times, least)
    first = words.where(F.lit(False)).select("word") if not most else spark.createDataFrame(pa.table({"word": pa.array([w for _, w in most], pa.binary())}))
    del most
    prob = head_odds(count_ranks(train, text, head))
    rare_words = words.join(F.broadcast(first), "word", "left_anti")
    spelled = rare_words.unionByName(first.where(F.col("word") != F.lit(END)).select("word", F.lit(1).cast("long").alias("n")))  # of the head, each word once
    model = train_speller(spelled, v)
    both = both.select(exchange.text_key("text").alias("key"), "*").groupBy("key").agg(F.sum("times").alias("rep"), F.max("asked").alias("asked"), F.first("text").alias("text")).where("key is not null")
    release(spark)
    # the notes are written before they meet the texts again, which frees the pairs' shuffle files first
    notes = durable(exchange.annotate(both, pair_values, pair_counts, ranked=True, ties=False, alone=True), "notes")
    release(spark)
    noted = durable(both.join(notes, "key").select("key", "text", "notes", F.col("rep").alias("times"), "asked"), "pairs")
    release(spark)
    known_bit = learn_known(noted, head, head_times, documents)
    shared = spark.sparkContext.broadcast((model, head, times, prob, known_bit, head_times))
    below, buckets = np.log10(n + 1.0 * (v + 1)), width(spark)

    def run(batches):
        model, head, times, prob, known_bit, head_times = shared.value
        memory: dict[int, float] = {}
        credit = np.log10(times + 1)
        credit[HEAD] = 0
        end_known, end_base = int(times[head.end] > 0), float(credit[head.end])
        for batch in batches:
            raw, notes = flat.as_bytes(batch.column(1)), batch.column(2).to_pylist()
            cols: dict[str, list] = {c: [] for c in ("n_tokens", "n_bytes", "known", "base", "score", "rare")}
            for i, j, w, h, rank, kind, end_kind in _pieces(raw, head, SMALL):
                m, text = j - i, w.raw.tobytes()
                t = Stream(w, h, kind, end_kind)
                c, total = COUNT_OF[_dealt(t, notes[i:j], buckets)], totals(t, head_times, rank, documents)
                pair = (c > 0) & (total > 0)
                p = known_bit.probability(t, total, pair)
                bits = np.where(total > 0, np.log2(np.where(pair, p * np.minimum(1, c / np.maximum(total, 1)), 1 - p)), 0.0)
                each = prob[kind, rank].astype(np.float64)
                fresh = np.flatnonzero((rank == HEAD) & ~pair[t.at])  # words to spell
                if len(fresh):
                    own, at, of = np.unique(h[fresh], return_index=True, return_inverse=True)
                    hashes = own.tolist()
                    new = [k for k, x in enumerate(hashes) if x not in memory]
                    got = dict(zip([hashes[k] for k in new], model.score([text[w.start[x] : w.end[x]] for x in fresh[at[new]].tolist()]).tolist())) if new else {}
                    spelled = np.array([got[x] if x in got else memory[x] for x in hashes])
                    if len(memory) < 200_000:
                        memory.update(got)
                    each[fresh] += spelled[of]
                scratch = np.empty(len(t.h))
                scratch[t.at], scratch[t.ends] = each, prob[end_kind, head.end]
                score = np.bincount(t.doc, bits + np.where(pair, 0.0, scratch), minlength=m)
                cols["known"] += (np.bincount(w.doc, (rank < HEAD) & (times[rank] > 0), minlength=m).astype(np.int64) + end_known).tolist()
                cols["base"] += (np.bincount(w.doc, credit[rank], minlength=m) + end_base).tolist()
                cols["n_tokens"] += (w.count + 1).tolist()
                cols["n_bytes"] += np.diff(w.doc_at).tolist()
                cols["score"] += (score * np.log10(2)).tolist()
                out = np.flatnonzero(rank == HEAD)
                bounds = np.searchsorted(w.doc[out], np.arange(m + 1)).tolist()
                found = [text[x:y] for x, y in zip(w.start[out].tolist(), w.end[out].tolist())]
                cols["rare"] += [found[x:y] for x, y in zip(bounds, bounds[1:])]
            kinds = {"n_tokens": pa.int64(), "n_bytes": pa.int64(), "known": pa.int64(), "base": pa.float64(), "score": pa.float64(), "rare": pa.list_(pa.binary())}
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(cols[c], kinds[c]) for c in kinds]], ["key", *kinds])

    asked = noted.where("asked > 0").select("key", "text", "notes")
    scored = durable(asked.mapInArrow(run, "key binary, n_tokens long, n_bytes long, known long, base double, score double, rare array<binary>"), "scored")
    rare = scored.where(F.size("rare") > 0).select("key", F.explode("rare").alias("word"))
    tail = rare.join(rare_words, "word").groupBy("key").agg(F.count("*").alias("more"), F.sum(F.log10(F.col("n") + 1.0)).alias("add"))
    by_text = scored.drop("rare").join(tail, "key", "left")
    rows = docs.select(F.col(doc_id).alias("doc_id"), full).select("doc_id", exchange.text_key("text").alias("key"))
    return rows.join(by_text, "key", "left").select(
        "doc_id",
        "n_tokens",
        (F.col("known") + F.coalesce("more", F.lit(0))).cast("long").alias("n_known"),
        F.lit(n).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("add", F.lit(0.0)) - F.col("n_tokens") * F.lit(float(below))).alias("base_score"),
        "score",
        F.try_divide(-F.col("score") / F.lit(float(np.log10(2))), F.col("n_bytes")).alias("bits_per_byte"),
    )


def op2(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").withColumn("held_out", F.coalesce(fold("doc_id", 7) == 2, F.lit(False)))
    out = score_texts(docs, ~F.col("held_out"))
    return out.select("doc_id", F.coalesce(fold("doc_id", 7) == 2, F.lit(False)).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score", "bits_per_byte")
