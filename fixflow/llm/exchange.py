"""Counting what a corpus repeats, with answers returned to the documents.

``annotate`` hashes every document into a sequence of 64-bit values (shingles, windows, phrases), deals the values of the
whole corpus out by value, lets a function look at all values of a bucket together and brings one byte for each value back
to its document. Values travel as packed arrays: 4 bytes each (the bucket has the other bits), or 12 with a second hash, without
row overhead. Both directions carry everything that's needed in the rows themselves, so a lost task can be run again anywhere.

The number of buckets is the session's shuffle width, so a bucket has a bounded share of the values at every size. A value
that fills a bucket (a passage in a third of all documents) adds 4 bytes for each place, never pairs.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import flat
from .common import width

CHUNK = 1 << 19  # values that travel together
NARROW, WIDE = np.dtype([("low", "<u4")]), np.dtype([("low", "<u4"), ("more", "<u8")])
RANK = np.dtype([("rep", "<i8"), ("tie", "<u8")])
LAST = 2**63 - 1  # rank of a document without an id


def distinct_texts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """key (digest of the text), rep (smallest id, null if none), copies, text: one row for each text that isn't null.

    Copies are combined before the shuffle, so the text of a group that makes up a third of all rows moves once a task.
    """
    return (
        docs.where(F.col(text).isNotNull())
        .select(text_key(text).alias("key"), F.col(doc_id).cast("long").alias("rep"), F.col(text).alias("text"))
        .groupBy("key")
        .agg(F.min("rep").alias("rep"), F.count("*").alias("copies"), F.first("text").alias("text"))
        .where("key is not null")  # as a join on key adds: both readers of this plan then share one shuffle
    )


def text_key(text: str):
    return F.unhex(F.md5(F.col(text).cast("binary")))


def bucket_of(h: np.ndarray, n: int) -> np.ndarray:
    return (((h >> np.uint64(32)) * np.uint64(n)) >> np.uint64(32)).astype(np.uint16 if n <= 1 << 16 else np.uint32)


class Values:
    """The values of some texts: h in document order, count of each text, and optionally a second hash and a 0/1 flag."""

    def __init__(self, h: np.ndarray, count: np.ndarray, more: np.ndarray | None = None, flag: np.ndarray | None = None):
        self.h, self.count, self.more, self.flag = h, count, more, flag


def _pack(vs: list[Values], keys: list[bytes], ranks: np.ndarray | None, n: int, chunk: int) -> pa.RecordBatch:
    """Rows for the buckets of one chunk of documents; the row of bucket 0 also has the documents' keys."""
    h, c = np.concatenate([v.h for v in vs]), np.concatenate([v.count for v in vs])
    b = bucket_of(h, n)
    order = np.argsort(b, kind="stable")
    b = b[order]
    doc = np.repeat(np.arange(len(c), dtype=np.int64), c)[order]
    value = np.empty(len(h), NARROW if vs[0].more is None else WIDE)
    value["low"] = h[order].astype(np.uint32)
    if vs[0].more is not None:
        value["more"] = np.concatenate([v.more for v in vs])[order]
    flag = None if vs[0].flag is None else np.concatenate([v.flag for v in vs])[order]
    cut = np.flatnonzero(np.diff(b.astype(np.int64), prepend=-1)).tolist()
    parts = [(int(b[i]), i, j) for i, j in zip(cut, [*cut[1:], len(b)])]
    if not parts or parts[0][0]:
        parts.insert(0, (0, 0, 0))
    out: dict[str, list] = {x: [] for x in ("bucket", "chunk", "value", "doc", "flag", "rank", "keys")}
    for name, i, j in parts:
        step = np.diff(doc[i:j], prepend=0)
        out["bucket"].append(name)
        out["chunk"].append(chunk)
        out["value"].append(value[i:j].tobytes())
        out["doc"].append(step.astype(np.uint32 if len(c) > 65535 else np.uint16).tobytes())
        out["flag"].append(None if flag is None else np.packbits(flag[i:j]).tobytes())
        if ranks is not None:
            step[:1] = 1
            out["rank"].append(ranks[doc[i:j][step > 0]].tobytes())
        else:
            out["rank"].append(None)
        out["keys"].append(b"".join(keys) if name == 0 else None)
    kinds = [("bucket", pa.int32()), ("chunk", pa.int64()), *[(x, pa.binary()) for x in ("value", "doc", "flag", "rank", "keys")]]
    return pa.RecordBatch.from_pydict(out, pa.schema(kinds))


def annotate(
    texts: DataFrame,
    hasher: Callable[..., Values],
    judge: Callable[..., np.ndarray],
    ranked: bool = False,
    wide: bool = False,
    extra: str | None = None,
    ties: bool = True,
    alone: bool = False,
) -> DataFrame:
    """texts (key, rep, text, ...) with `notes` binary: judge's byte for each of the document's values. alone: only key and notes.

    hasher(texts, extras) -> Values (with a second hash if ``wide``). judge(values, flags, ranks) -> uint8 for each value of a bucket; with ``ranked``
    ranks has the id (and a tie-breaker, 0 without ``ties``) of each value's document. Notes are in the order that ``deal`` undoes.
    """
    n, kind = width(texts.sparkSession), WIDE if wide else NARROW

    def send(batches):
        from pyspark import TaskContext

        task, k = TaskContext.get().partitionId(), 0
        vs, keys, ranks, size = [], [], [], 0

        def flush():
            return _pack(vs, keys, np.concatenate(ranks) if ranked else None, n, (task << 32) | k)

        for batch in batches:
            ids, raw, more = batch.column(0).to_pylist(), flat.as_bytes(batch.column(2)), batch.column(3).to_pylist()
            rank = np.empty(len(ids), RANK)
            rank["rep"] = batch.column(1).fill_null(LAST).to_numpy()
            rank["tie"] = [int.from_bytes(x[:8], "big") for x in ids] if ties else 0
            for i, j in flat.parts(raw):
                vs.append(hasher(raw[i:j], more[i:j]))
                keys += ids[i:j]
                ranks.append(rank[i:j])
                size += len(vs[-1].h)
                if size >= CHUNK:
                    yield flush()
                    vs, keys, ranks, size, k = [], [], [], 0, k + 1
        if keys:
            yield flush()

    def look(pdf: pd.DataFrame) -> pd.DataFrame:
        values = [np.frombuffer(x, kind) for x in pdf["value"]]
        lens = [len(x) for x in values]
        flags = None if pdf["flag"].iloc[0] is None else np.concatenate([np.unpackbits(np.frombuffer(x, np.uint8), count=m) for x, m in zip(pdf["flag"], lens)])
        ranks = None
        if ranked:
            per = []
            for x, d, m in zip(pdf["rank"], pdf["doc"], lens):
                step = np.frombuffer(d, np.uint16 if len(d) == 2 * m else np.uint32).copy()
                step[:1] = 1
                per.append(np.frombuffer(x, RANK)[np.cumsum(step > 0) - 1])
            ranks = np.concatenate(per)
        notes = judge(np.concatenate(values), flags, ranks).astype(np.uint8)
        at = np.concatenate([[0], np.cumsum(lens)])
        return pd.DataFrame({"chunk": pdf["chunk"], "bucket": pdf["bucket"], "doc": pdf["doc"], "keys": pdf["keys"], "notes": [notes[i:j].tobytes() for i, j in zip(at, at[1:])]})

    def gather(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("bucket")
        raw = pdf["keys"].iloc[0]
        keys = [raw[i : i + 16] for i in range(0, len(raw), 16)]
        steps = np.uint32 if len(keys) > 65535 else np.uint16
        doc = np.concatenate([np.cumsum(np.frombuffer(x, steps).astype(np.int64)) for x in pdf["doc"]])
        notes = np.concatenate([np.frombuffer(x, np.uint8) for x in pdf["notes"]])
        notes = notes[np.argsort(doc, kind="stable")]
        at = np.concatenate([[0], np.cumsum(np.bincount(doc, minlength=len(keys)))])
        return pd.DataFrame({"key": keys, "notes": [notes[i:j].tobytes() for i, j in zip(at, at[1:])]})

    cols = texts.select("key", "rep", "text", F.col(extra) if extra else F.lit(None).cast("binary").alias("extra"))
    sent = cols.mapInArrow(send, "bucket int, chunk long, value binary, doc binary, flag binary, rank binary, keys binary")
    judged = sent.groupBy("bucket").applyInPandas(look, "chunk long, bucket int, doc binary, keys binary, notes binary")
    if alone:
        return judged.groupBy("chunk").applyInPandas(gather, "key binary, notes binary")
    return texts.join(judged.groupBy("chunk").applyInPandas(gather, "key binary, notes binary"), "key")


def deal(h: np.ndarray, n: int, notes: bytes) -> np.ndarray:
    """The notes of one document in the order of its values h; n: the shuffle width that annotate saw."""
    out = np.empty(len(h), np.uint8)
    got = np.frombuffer(notes, np.uint8)
    if len(got) != len(h):
        raise ValueError(f"{len(got)} notes for {len(h)} values")
    out[np.argsort(bucket_of(h, n), kind="stable")] = got
    return out


def sorted_low(low: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Stable order of 32-bit values and the values in it; one sort of value and place together is faster than a stable argsort."""
    both = low.astype(np.uint64) << np.uint64(32) | np.arange(len(low), dtype=np.uint64)
    both.sort()
    return (both & np.uint64(0xFFFFFFFF)).astype(np.int64), (both >> np.uint64(32)).astype(np.uint32)


def times(low: np.ndarray) -> np.ndarray:
    """How often each value stands in the array."""
    order, s = sorted_low(low)
    cut = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]])) if len(s) else np.zeros(0, np.int64)
    n = np.diff(np.append(cut, len(s)))
    out = np.empty(len(s), np.int64)
    out[order] = np.repeat(n, n)
    return out


def annotate_bodies(
    texts: DataFrame,
    hasher: Callable[..., tuple[np.ndarray, np.ndarray, np.ndarray, list[bytes]]],
    judge: Callable[[list[bytes], np.ndarray, np.ndarray], list[np.ndarray]],
    extra: str | None = None,
) -> DataFrame:
    """As ``annotate`` for pieces of text: those dealt to one bucket are looked at together.

    hasher(texts, extras) -> for each piece the value that deals it out and a content hash, the number of pieces of each text, and
    the pieces. Equal pieces of a chunk travel once. judge(distinct pieces, how often each stands, the value of each) -> notes of each.
    """
    n = width(texts.sparkSession)

    def pack(hs, contents, counts, bodies, keys, chunk):
        h, content, c = np.concatenate(hs), np.concatenate(contents), np.concatenate(counts)
        b = bucket_of(h, n)
        order = np.argsort(b, kind="stable")
        b, doc = b[order], np.repeat(np.arange(len(c), dtype=np.int64), c)[order]
        cut = np.flatnonzero(np.diff(b.astype(np.int64), prepend=-1)).tolist()
        parts = [(int(b[i]), i, j) for i, j in zip(cut, [*cut[1:], len(b)])]
        if not parts or parts[0][0]:
            parts.insert(0, (0, 0, 0))
        out: dict[str, list] = {x: [] for x in ("bucket", "chunk", "pick", "doc", "lens", "body", "content", "value", "keys")}
        for name, i, j in parts:
            own, first, pick = np.unique(content[order[i:j]], return_index=True, return_inverse=True)
            sent = [bodies[k] for k in order[i:j][first].tolist()]
            out["bucket"].append(name)
            out["chunk"].append(chunk)
            out["pick"].append(pick.astype(np.uint32).tobytes())
            out["doc"].append(np.diff(doc[i:j], prepend=0).astype(np.uint32).tobytes())
            out["lens"].append(np.array([len(x) for x in sent], np.uint32).tobytes())
            out["body"].append(b"".join(sent))
            out["content"].append(own.tobytes())
            out["value"].append(h[order[i:j][first]].tobytes())
            out["keys"].append(b"".join(keys) if name == 0 else None)
        kinds = [("bucket", pa.int32()), ("chunk", pa.int64()), *[(x, pa.binary()) for x in ("pick", "doc", "lens", "body", "content", "value", "keys")]]
        return pa.RecordBatch.from_pydict(out, pa.schema(kinds))

    def send(batches):
        from pyspark import TaskContext

        task, k = TaskContext.get().partitionId(), 0
        acc: tuple[list, ...] = ([], [], [], [], [])
        size = 0
        for batch in batches:
            ids, raw, more = batch.column(0).to_pylist(), flat.as_bytes(batch.column(1)), batch.column(2).to_pylist()
            for i, j in flat.parts(raw):
                h, content, count, bodies = hasher(raw[i:j], more[i:j])
                for to, x in zip(acc[:3], (h, content, count)):
                    to.append(x)
                acc[3].extend(bodies)
                acc[4].extend(ids[i:j])
                size += sum(map(len, bodies))
                if size >= 16 * CHUNK:
                    yield pack(*acc, (task << 32) | k)
                    acc, size, k = ([], [], [], [], []), 0, k + 1
        if acc[4]:
            yield pack(*acc, (task << 32) | k)

    def look(pdf: pd.DataFrame) -> pd.DataFrame:
        content = np.concatenate([np.frombuffer(x, np.uint64) for x in pdf["content"]])
        own, first, of = np.unique(content, return_index=True, return_inverse=True)
        bodies = []
        for lens, body in zip(pdf["lens"], pdf["body"]):
            at = [0, *np.cumsum(np.frombuffer(lens, np.uint32)).tolist()]
            bodies += [body[i:j] for i, j in zip(at, at[1:])]
        base, picks = 0, []
        for x, p in zip(pdf["content"], pdf["pick"]):
            picks.append(of[base + np.frombuffer(p, np.uint32).astype(np.int64)])
            base += len(x) // 8
        many = np.bincount(np.concatenate(picks), minlength=len(own)) if len(own) else np.zeros(0, np.int64)
        value = np.concatenate([np.frombuffer(x, np.uint64) for x in pdf["value"]])
        notes = judge([bodies[k] for k in first.tolist()], many, value[first])
        sizes = np.array([len(x) for x in notes], np.uint32)
        found = [x.tobytes() for x in notes]
        return pd.DataFrame({"chunk": pdf["chunk"], "bucket": pdf["bucket"], "doc": pdf["doc"], "keys": pdf["keys"], "sizes": [sizes[p].tobytes() for p in picks], "notes": [b"".join([found[k] for k in p.tolist()]) for p in picks]})

    def gather(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("bucket")
        raw = pdf["keys"].iloc[0]
        parts: list[list[bytes]] = [[] for _ in range(len(raw) // 16)]
        for doc, sizes, notes in zip(pdf["doc"], pdf["sizes"], pdf["notes"]):
            at = [0, *np.cumsum(np.frombuffer(sizes, np.uint32)).tolist()]
            for d, i, j in zip(np.cumsum(np.frombuffer(doc, np.uint32)).tolist(), at, at[1:]):
                parts[d].append(notes[i:j])
        return pd.DataFrame({"key": [raw[i : i + 16] for i in range(0, len(raw), 16)], "notes": [b"".join(x) for x in parts]})

    cols = texts.select("key", "text", F.col(extra) if extra else F.lit(None).cast("binary").alias("extra"))
    sent = cols.mapInArrow(send, "bucket int, chunk long, pick binary, doc binary, lens binary, body binary, content binary, value binary, keys binary")
    judged = sent.groupBy("bucket").applyInPandas(look, "chunk long, bucket int, doc binary, keys binary, sizes binary, notes binary")
    return texts.join(judged.groupBy("chunk").applyInPandas(gather, "key binary, notes binary"), "key")
