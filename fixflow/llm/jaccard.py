"""Exact n-gram Jaccard join by token-combination prefixes.

A document is its set of word shingles. Shingles are ordered from rare to frequent by how many documents hold them (counted
over the whole corpus, see ``exchange``). Two sets that reach the threshold share at least ``1 + g`` shingles of their
prefixes when those are extended by ``g``; so they share a rare shingle, or two frequent ones of the same of ``g``
subclasses. Rare shingles are therefore indexed alone and frequent ones by pairs inside a subclass. The number of
subclasses follows the set size in bands as wide as the threshold allows; a document uses its own band and the next, so
partners meet. A shingle that one document alone holds is not indexed.

A signature with few documents gives candidate pairs. One with many (a family of near copies, or boilerplate) gives one edge to its
smallest member; connected members form a family, compared block by block in numpy, where only a spanning forest of the found links leaves
a task. Candidates are verified on whole sets of 64-bit shingle hashes. Links join into components.

Copies of a text are one node (its smallest id). Null or empty texts have no shingles and no links. Rows with a null id
get the component of their text if another row has an id, else null. Rows that share an id count as one document for links. An empty table
gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import exchange, flat
from .common import durable, table, width
from .graph import components

RARE = 5  # shingles in at most 2**RARE documents are indexed alone
FEW = 1 << RARE  # most documents of a signature whose pairs are candidates
BLOCK = 512


def shingler(k: int):
    """texts -> distinct shingle hashes of each (sorted), and their number."""

    def run(texts: list[bytes], _=None) -> exchange.Values:
        w = flat.Words(texts, fold=True)
        hashes = flat.Runs(w.hashes(11), 12)
        at = w.windows(k)
        short = np.flatnonzero((w.count > 0) & (w.count < k))
        h = hashes(at, at + k)
        n = w.windows_of(at)
        ends = np.cumsum(n)
        parts = [np.unique(h[i:j]) for i, j in zip((ends - n).tolist(), ends.tolist())]
        for d in short.tolist():
            parts[d] = hashes(w.first[d : d + 1], w.first[d + 1 : d + 2])
        return exchange.Values(np.concatenate(parts) if parts else h, np.fromiter(map(len, parts), np.int64, len(parts)))

    return run


def rarity(values: np.ndarray, flags, ranks) -> np.ndarray:
    """0 for a value that stands once, else the number of binary digits of its count less one."""
    return np.ceil(np.log2(exchange.times(values["low"]))).astype(np.uint8)


def band_of(n: int, percent: int) -> int:
    return int(np.floor(np.log(n) / -np.log(percent / 100 - 0.001)))


def subclasses(band: int, percent: int) -> int:
    return 1 + int((1 - percent / 100) * np.exp(-np.log(percent / 100 - 0.001) * band) / 6)


def signatures(h: np.ndarray, rare: np.ndarray, percent: int) -> np.ndarray:
    """Signatures of a set of hashes h whose document counts have the digits `rare`."""
    n = len(h)
    if n == 0:
        return np.zeros(0, np.uint64)
    least = (percent * n + 99) // 100
    if n == 1:
        return flat.mix(h ^ np.uint64(1)) if rare[0] else np.zeros(0, np.uint64)
    band = band_of(n, percent)
    order = np.lexsort((h, rare))
    h, rare = h[order], rare[order]
    out = []
    widest = max(subclasses(band, percent), subclasses(band + 1, percent))
    head = slice(0, n - least + 1 + widest)
    out.append(flat.mix(h[head][(rare[head] > 0) & (rare[head] <= RARE)] ^ np.uint64(1)))
    for b in (band, band + 1):
        g = subclasses(b, percent)
        often = h[: n - least + 1 + g][rare[: n - least + 1 + g] > RARE]
        if len(often) < 2:
            continue
        sub = often % np.uint64(g)
        o = np.lexsort((often, sub))
        often, sub = often[o], sub[o]
        lag = 1
        while lag < len(often):
            same = sub[lag:] == sub[:-lag]
            if not same.any():
                break
            out.append(flat.mix(often[:-lag][same] * np.uint64(0x9E3779B97F4A7C15) + flat.mix(often[lag:][same]) + np.uint64(2 + b)))
            lag += 1
    return np.unique(np.concatenate(out))


def linked(shared, n_a, n_b, percent: int):
    return 100 * shared >= percent * (n_a + n_b - shared)


class Forest:
    """Union-find over positions."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def _with_sets(texts: DataFrame, k: int, percent: int) -> DataFrame:
    """key, rep, n, hashes and sigs (null for sets that can have no partner)."""
    n = width(texts.sparkSession)
    shingles = shingler(k)

    def run(batches):
        for batch in batches:
            key, rep, raw, notes = batch.column(0), batch.column(1), flat.as_bytes(batch.column(2)), batch.column(3).to_pylist()
            size, hs, sigs = [], [], []
            for i, j in flat.parts(raw):
                v = shingles(raw[i:j])
                h, c = v.h, v.count
                ends = np.cumsum(c)
                for d, (p, q) in enumerate(zip((ends - c).tolist(), ends.tolist())):
                    own = h[p:q]
                    s = signatures(own, exchange.deal(own, n, notes[i + d]), percent)
                    size.append(q - p)
                    hs.append(own.tobytes() if len(s) else None)
                    sigs.append(s.tobytes() if len(s) else None)
            yield pa.RecordBatch.from_arrays([key, rep, pa.array(size, pa.int64()), pa.array(hs, pa.binary()), pa.array(sigs, pa.binary())], ["key", "rep", "n", "hashes", "sigs"])

    noted = exchange.annotate(texts, shingles, rarity)
    return noted.select("key", "rep", "text", "notes").mapInArrow(run, "key binary, rep long, n long, hashes binary, sigs binary")


def _candidates(sets: DataFrame, percent: int) -> DataFrame:
    """a, b, many: pairs of ids that share a signature, or edges to the smallest id of a signature that many share."""
    n = width(sets.sparkSession)

    def send(batches):
        for batch in batches:
            sigs = [np.frombuffer(x, np.uint64) for x in batch.column(2).to_pylist()]
            if not sigs:
                continue
            lens = np.fromiter(map(len, sigs), np.int64, len(sigs))
            s = np.concatenate(sigs)
            rep, size = (np.repeat(batch.column(c).to_numpy(zero_copy_only=False), lens) for c in (0, 1))
            b = exchange.bucket_of(s, n)
            order = np.argsort(b, kind="stable")
            cut = np.flatnonzero(np.diff(b[order].astype(np.int64), prepend=-1)).tolist()
            for i, j in zip(cut, [*cut[1:], len(order)]):
                o = order[i:j]
                yield pa.RecordBatch.from_pydict({"bucket": [int(b[o[0]])], "sig": [s[o].tobytes()], "rep": [rep[o].tobytes()], "n": [size[o].tobytes()]}, pa.schema([("bucket", pa.int32()), ("sig", pa.binary()), ("rep", pa.binary()), ("n", pa.binary())]))

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        s, rep, size = (np.concatenate([np.frombuffer(x, kind) for x in pdf[c]]) for c, kind in (("sig", np.uint64), ("rep", np.int64), ("n", np.int64)))
        order = np.lexsort((rep, s))
        s, rep, size = s[order], rep[order], size[order]
        cut = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
        m = np.diff(np.append(cut, len(s)))
        of = np.repeat(np.arange(len(cut)), m)
        few = (m <= FEW)[of]
        pairs = []
        for lag in range(1, FEW):
            i = np.flatnonzero(few[:-lag] & (s[lag:] == s[:-lag])) if lag < len(s) else np.zeros(0, np.int64)
            if not len(i):
                break
            lo, hi = np.minimum(size[i], size[i + lag]), np.maximum(size[i], size[i + lag])
            i = i[(100 * lo >= percent * hi) & (rep[i] != rep[i + lag])]
            pairs.append(np.stack([rep[i], rep[i + lag]], 1))
        many = np.flatnonzero(~few & (rep != rep[cut][of]))
        stars = np.unique(np.stack([rep[cut][of[many]], rep[many]], 1), axis=0)
        pairs = np.unique(np.concatenate(pairs), axis=0) if pairs else np.zeros((0, 2), np.int64)
        both = np.concatenate([pairs, stars])
        return pd.DataFrame({"a": both[:, 0], "b": both[:, 1], "many": np.arange(len(both)) >= len(pairs)})

    sent = sets.where("sigs is not null and rep is not null").select("rep", "n", "sigs").mapInArrow(send, "bucket int, sig binary, rep binary, n binary")
    return sent.groupBy("bucket").applyInPandas(meet, "a long, b long, many boolean").distinct()


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    def check(batches):
        for batch in batches:
            a, b, x, y = (batch.column(k) for k in range(4))
            keep = []
            for p, q in zip(x.to_pylist(), y.to_pylist()):
                p, q = np.frombuffer(p, np.uint64), np.frombuffer(q, np.uint64)
                both = np.concatenate([p, q])
                both.sort()
                keep.append(bool(linked(int((both[1:] == both[:-1]).sum()), len(p), len(q), percent)))
            yield pa.RecordBatch.from_arrays([a, b], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    own = sets.where("hashes is not null and rep is not null")
    sides = pairs.join(own.select(F.col("rep").alias("a"), F.col("hashes").alias("x")), "a").join(own.select(F.col("rep").alias("b"), F.col("hashes").alias("y")), "b")
    return sides.select("a", "b", "x", "y").mapInArrow(check, "a long, b long")


def _overlaps(xs: list[np.ndarray], ys: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections of two lists of sets."""
    flat_x, flat_y = np.concatenate(xs), np.concatenate(ys)
    both, inv = np.unique(np.concatenate([flat_x, flat_y]), return_inverse=True)
    on_x, on_y = np.zeros(len(both), bool), np.zeros(len(both), bool)
    on_x[inv[: len(flat_x)]] = True
    on_y[inv[len(flat_x) :]] = True
    shared = on_x & on_y
    col = np.cumsum(shared) - 1
    row_x, row_y = (np.repeat(np.arange(len(z)), [len(t) for t in z]) for z in (xs, ys))
    ix, iy = inv[: len(flat_x)], inv[len(flat_x) :]
    kx, ky = shared[ix], shared[iy]
    row_x, cx, row_y, cy = row_x[kx], col[ix[kx]], row_y[ky], col[iy[ky]]
    out = np.zeros((len(xs), len(ys)), np.float32)
    total = int(shared.sum())
    for i in range(0, total, 8192):
        a, b = np.zeros((len(xs), min(8192, total - i)), np.float32), np.zeros((len(ys), min(8192, total - i)), np.float32)
        m = (cx >= i) & (cx < i + 8192)
        a[row_x[m], cx[m] - i] = 1
        m = (cy >= i) & (cy < i + 8192)
        b[row_y[m], cy[m] - i] = 1
        out += a @ b.T
    return out.astype(np.int64)


def _family_links(stars: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Spanning forests of the links inside families, from comparisons of blocks of a family."""
    families = components(stars).withColumnRenamed("node", "rep")
    blocks = families.groupBy("component").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("nb"))
    placed = (
        families.join(blocks, "component")
        .withColumn("i", F.pmod(F.xxhash64("rep"), F.col("nb")).cast("int"))
        .join(sets.where("hashes is not null").select("rep", "hashes"), "rep")
        .withColumn("j", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
        .select("component", F.least("i", "j").alias("p"), F.greatest("i", "j").alias("q"), "i", "rep", "hashes")
    )

    def compare(pdf: pd.DataFrame) -> pd.DataFrame:
        p, q = int(pdf["p"].iloc[0]), int(pdf["q"].iloc[0])
        pdf = pdf.sort_values("rep")
        reps = pdf["rep"].to_numpy()
        sets_ = [np.frombuffer(x, np.uint64) for x in pdf["hashes"]]
        left, right = np.flatnonzero(pdf["i"] == p), np.flatnonzero(pdf["i"] == q)
        found, forest = [], Forest(len(reps))
        if len(left) and len(right):
            size = np.array([len(x) for x in sets_])
            shared = _overlaps([sets_[t] for t in left], [sets_[t] for t in right])
            for x, y in zip(*np.nonzero(linked(shared, size[left][:, None], size[right][None, :], percent))):
                if left[x] != right[y] and forest.join(left[x], right[y]):
                    found.append((reps[left[x]], reps[right[y]]))
        return pd.DataFrame(found, columns=["a", "b"], dtype="int64")

    return placed.groupBy("component", "p", "q").applyInPandas(compare, "a long, b long")


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80, doc_id: str = "doc_id", text: str = "text", with_key: bool = False) -> DataFrame:
    """doc_id, n_shingles, component_id: documents whose sets of k-word shingles are `percent` alike are linked. with_key: and the digest of the row's text."""
    sets = durable(_with_sets(exchange.distinct_texts(docs, doc_id, text), k, percent), "sets")
    found = durable(_candidates(sets, percent), "candidates")
    links = _verified(found.where("not many").select("a", "b"), sets, percent)
    stars = found.where("many").select("a", "b")
    if not stars.isEmpty():
        links = links.unionByName(_family_links(stars, sets, percent))
    of = components(links).withColumnRenamed("node", "rep")
    by_text = sets.select("key", "rep", "n").join(of, "rep", "left").select("key", "n", F.coalesce("component", "rep").alias("component"), F.col("rep").alias("text_rep"))
    rows = docs.select(F.col(doc_id).alias("doc_id"), exchange.text_key(text).alias("key"))
    full = F.coalesce(F.col("n"), F.lit(0)).cast("long")
    return rows.join(by_text, "key", "left").select("doc_id", full.alias("n_shingles"), F.when(full > 0, F.col("component")).otherwise(F.col("doc_id").cast("long")).alias("component_id"), *(["key"] if with_key else []))


def op7(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), k=4, percent=85)
