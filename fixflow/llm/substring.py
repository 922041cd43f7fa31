"""Substring dedup by fixed-block anchors.

A window of ``window`` words holds a whole block of ``window // 2`` words wherever the blocks of its text are cut, so if two windows
are equal, a block of either text is met by a rolling probe of the other. All non-overlapping blocks of the corpus form
the index and every rolling run of a block's length probes it (both dealt out by hash, see ``exchange``). Only windows
around a hit are looked at again: by two independent hashes of the whole window, 100 bits or more, they find out whether
an equal window starts earlier. Windows that touch make up the maximal repeats, whose words go.

Copies of a text are looked at once: in every copy but the first all windows start earlier too.

Nulls: a null or empty text has no words and loses none. Rows without an id come last and count as one document, like
rows that share an id. Texts are taken whole at any length. An empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import exchange, flat
from .common import durable, table, width

NOTHING = hashlib.sha256(b"").hexdigest()


def anchors(window: int):
    """Hashes of all rolling runs of a block's length; the flag marks the runs that are blocks of the index."""
    block = window // 2

    def run(texts: list[bytes], _=None) -> exchange.Values:
        w = flat.Words(texts)
        at = w.windows(block)
        at = at[w.count[w.doc[at]] >= window]
        h = flat.Runs(w.hashes(21), 22)(at, at + block)
        return exchange.Values(h, w.windows_of(at), flag=((at - w.first[w.doc[at]]) % block == 0).astype(np.uint8))

    return run


def hits(values: np.ndarray, flags: np.ndarray, ranks) -> np.ndarray:
    """1 for values that stand more than once and are in the index."""
    low = values["low"]
    order = np.argsort(low, kind="stable")
    s = low[order]
    cut = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]])) if len(s) else np.zeros(0, np.int64)
    if not len(cut):
        return np.zeros(0, np.uint8)
    n = np.diff(np.append(cut, len(s)))
    good = (n > 1) & (np.add.reduceat(flags[order].astype(np.int64), cut) > 0)
    out = np.empty(len(s), np.uint8)
    out[order] = np.repeat(good, n)
    return out


def wanted_windows(window: int):
    """Two hashes of the windows that `extra` (packed bits over window starts) marks."""

    def run(texts: list[bytes], marks: list[bytes]) -> exchange.Values:
        w = flat.Words(texts)
        own = [np.flatnonzero(np.unpackbits(np.frombuffer(m, np.uint8), count=max(0, c - window + 1))) for m, c in zip(marks, w.count.tolist())]
        n = np.fromiter(map(len, own), np.int64, len(own))
        at = np.concatenate(own) + np.repeat(w.first[:-1], n) if own else np.zeros(0, np.int64)
        return exchange.Values(flat.Runs(w.hashes(23), 24)(at, at + window), n, more=flat.Runs(w.hashes(25), 26)(at, at + window))

    return run


def not_first(values: np.ndarray, flags, ranks: np.ndarray) -> np.ndarray:
    """1 for values of which an equal one stands in an earlier document, or earlier in the same one."""
    order = np.lexsort((np.arange(len(values)), ranks["tie"], ranks["rep"], values["more"], values["low"]))
    v = values[order]
    out = np.empty(len(v), np.uint8)
    out[order] = np.concatenate([[False], (v["low"][1:] == v["low"][:-1]) & (v["more"][1:] == v["more"][:-1])]) if len(v) else 0
    return out


def covered(at: np.ndarray, window: int, n: int) -> np.ndarray:
    """Which of n places lie in a window that starts at one of `at`."""
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + window, -1)
    return np.cumsum(edge[:-1]) > 0


def _probed(texts: DataFrame, window: int) -> DataFrame:
    """key, rep, n_words and, for texts with windows to look at again, text and marks."""
    n, values, block = width(texts.sparkSession), anchors(window), window // 2

    def run(batches):
        for batch in batches:
            raw, notes = flat.as_bytes(batch.column(2)), batch.column(3).to_pylist()
            words, sha, text, marks = [], [], [], []
            for i, j in flat.parts(raw):
                v = values(raw[i:j])
                ends = np.cumsum(v.count)
                for d, (p, q) in enumerate(zip((ends - v.count).tolist(), ends.tolist())):
                    own = raw[i + d].split()
                    hit = np.flatnonzero(exchange.deal(v.h[p:q], n, notes[i + d])) if any(notes[i + d]) else ()
                    words.append(len(own))
                    if len(hit):
                        near = covered(np.maximum(0, hit - (window - block)), window - block + 1, len(own) + window)[: len(own) - window + 1]
                    live = len(hit) and near.any()
                    text.append(raw[i + d].decode() if live else None)
                    marks.append(np.packbits(near).tobytes() if live else None)
                    sha.append(None if live else hashlib.sha256(b" ".join(own)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(words, pa.int64()), pa.array(sha, pa.string()), pa.array(text, pa.string()), pa.array(marks, pa.binary())], ["key", "rep", "n_words", "sha", "text", "marks"])

    noted = exchange.annotate(texts, values, hits)
    return noted.select("key", "rep", "text", "notes").mapInArrow(run, "key binary, rep long, n_words long, sha string, text string, marks binary")


def _cleaned(live: DataFrame, window: int, with_text: bool) -> DataFrame:
    """key, n_removed, kept_sha256 (and kept text) of the first copy of each text that may have repeats."""
    n, values = width(live.sparkSession), wanted_windows(window)

    def run(batches):
        for batch in batches:
            raw, marks, notes = flat.as_bytes(batch.column(1)), batch.column(2).to_pylist(), batch.column(3).to_pylist()
            gone, sha, kept = [], [], []
            for i, j in flat.parts(raw):
                v = values(raw[i:j], marks[i:j])
                w = flat.Words(raw[i:j])
                ends = np.cumsum(v.count)
                for d, (p, q) in enumerate(zip((ends - v.count).tolist(), ends.tolist())):
                    total = int(w.count[d])
                    starts = np.flatnonzero(np.unpackbits(np.frombuffer(marks[i + d], np.uint8), count=total - window + 1))
                    out = covered(starts[exchange.deal(v.h[p:q], n, notes[i + d]) > 0], window, total)
                    own = raw[i + d].split()
                    gone.append(int(out.sum()))
                    sha.append(hashlib.sha256(b" ".join([x for x, o in zip(own, out.tolist()) if not o])).hexdigest())
                    if with_text:  # cut from the start of each word that goes to the start of the next one
                        at = w.start[w.first[d] : w.first[d + 1]] - w.doc_at[d]
                        stay = np.repeat(np.concatenate([[True], ~out]), np.diff([0, *at.tolist(), len(raw[i + d])]))
                        kept.append(np.frombuffer(raw[i + d], np.uint8)[stay].tobytes().decode())
                    else:
                        kept.append(None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(gone, pa.int64()), pa.array(sha, pa.string()), pa.array(kept, pa.string())], ["key", "gone", "kept_sha", "kept"])

    noted = exchange.annotate(live, values, not_first, ranked=True, wide=True, extra="marks")
    return noted.select("key", "text", "marks", "notes").mapInArrow(run, "key binary, gone long, kept_sha string, kept string")


def remove_repeats(docs: DataFrame, window: int = 20, doc_id: str = "doc_id", text: str = "text", with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256; with_text: all columns of docs instead, with the text that is left."""
    probed = durable(_probed(exchange.distinct_texts(docs, doc_id, text), window), "anchors")
    cleaned = durable(_cleaned(probed.where("marks is not null").select("key", "rep", "text", "marks"), window, with_text), "repeats")
    by_text = probed.select("key", "rep", "n_words", "sha").join(cleaned, "key", "left")
    by_text = by_text.select(F.col("key").alias("__key"), F.col("rep").alias("__rep"), F.col("n_words").alias("__n"), F.coalesce("kept_sha", "sha").alias("__sha"), F.coalesce("gone", F.lit(0)).alias("__gone"), F.col("kept").alias("__kept"))
    first = F.col(doc_id).cast("long").eqNullSafe(F.col("__rep"))
    whole = ~first & (F.col("__n") >= window)
    if with_text:
        out = docs.withColumn("__key", exchange.text_key(text)).join(by_text, "__key", "left")
        new = F.when(F.col("__key").isNull(), F.col(text)).when(whole, F.lit("")).when(F.col("__gone") > 0, F.col("__kept")).otherwise(F.col(text))
        return out.select(*[new.alias(c) if c == text else F.col(f"`{c}`") for c in docs.columns])
    out = docs.select(F.col(doc_id).alias("doc_id"), exchange.text_key(text).alias("__key")).join(by_text, "__key", "left")
    first = F.col("doc_id").cast("long").eqNullSafe(F.col("__rep"))
    whole = ~first & (F.col("__n") >= window)
    return out.select(
        "doc_id",
        F.coalesce("__n", F.lit(0)).cast("long").alias("n_words"),
        F.when(whole, F.col("__n")).otherwise(F.coalesce("__gone", F.lit(0))).cast("long").alias("n_removed"),
        F.when(whole, F.lit(NOTHING)).otherwise(F.coalesce("__sha", F.lit(NOTHING))).alias("kept_sha256"),
    )


def op5(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"), 20)
