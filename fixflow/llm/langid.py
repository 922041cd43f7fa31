"""Language identification: multinomial naive Bayes over hashed character n-grams (1 to 3 code points).

Counts come from every labelled training row; the model is a matrix of ``BUCKETS`` x languages log-probabilities (its
size is fixed by those two numbers and is broadcast). Scoring is a sparse gather of that matrix in numpy: the buckets of
all n-grams of a batch lie in one flat array that is summed per document.

Nulls: a null text, or one without a letter, is ``und`` with score 0. Rows with a null label don't train. With no
training rows everything is ``und``. Extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship, table

BUCKETS = 1 << 16
MAX_LANGS = 2048
PIECE = 1 << 19  # code points handled at once
_letters: list[np.ndarray] = []


def letters() -> np.ndarray:
    if not _letters:
        _letters.append(np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000))
    return _letters[0]


def pieces(texts: list[str | None]):
    """Index ranges of texts with about PIECE code points each."""
    first = size = 0
    for i, t in enumerate(texts):
        n = len(t) if t else 0
        if i > first and size + n > PIECE:
            yield first, i
            first, size = i, 0
        size += n
    if texts:
        yield first, len(texts)


def grams(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all n-grams that end in a letter, and the document of each."""
    flat = np.frombuffer("\n".join([t or "" for t in texts] + [""]).encode("utf-32-le"), np.uint32)
    is_letter = letters()[flat]
    low = flat + 32 * (((flat >= 65) & (flat <= 90)) | ((flat >= 0xC0) & (flat <= 0xDE) & (flat != 0xD7))).astype(np.uint32)
    low = np.where(is_letter, low, np.uint32(32)).astype(np.uint64)
    starts = np.concatenate([[0], np.cumsum([len(t or "") + 1 for t in texts])])
    at = np.flatnonzero(is_letter)
    doc = np.searchsorted(starts, at, side="right") - 1
    a = low[at]
    b = np.where(at > 0, low[at - 1], 32)
    c = np.where((at > 1) & (b != 32), low[at - 2], 32)
    mul = np.uint64(0x9E3779B97F4A7C15)
    keys = [a * np.uint64(4) + np.uint64(1), (b << np.uint64(21) | a) * np.uint64(4) + np.uint64(2), (c << np.uint64(42) | b << np.uint64(21) | a) * np.uint64(4) + np.uint64(3)]
    out = np.stack([((k * mul) ^ (k * mul >> np.uint64(29))) * mul >> np.uint64(48) for k in keys], 1)
    return out.astype(np.int32), doc


def learn(train: DataFrame, text: str = "text", label: str = "lang") -> tuple[list[str], np.ndarray]:
    """(languages, log-probabilities [language, bucket] with the prior in the last column)."""
    named = sorted((r[0], r[1]) for r in train.where(F.col(label).isNotNull()).groupBy(F.col(label)).count().limit(MAX_LANGS + 1).collect())
    if len(named) > MAX_LANGS:
        raise ValueError(f"more than {MAX_LANGS} distinct labels")
    if not named:
        return [], np.zeros((0, BUCKETS + 1))
    ship(train.sparkSession)
    langs = [x for x, _ in named]
    number = {x: i for i, x in enumerate(langs)}

    def count(batches):
        total = np.zeros(len(langs) * BUCKETS, np.int64)
        for batch in batches:
            texts, of = batch.column(0).to_pylist(), np.array([number[x] for x in batch.column(1).to_pylist()], np.int64)
            for i, j in pieces(texts):
                g, doc = grams(texts[i:j])
                total += np.bincount((of[i:j][doc][:, None] * BUCKETS + g).ravel(), minlength=len(total))
        rows = total.reshape(-1, 4096)
        full = np.flatnonzero(rows.any(1))
        if len(full):
            from pyspark import TaskContext

            salt = TaskContext.get().partitionId() % 64
            yield pa.RecordBatch.from_arrays([pa.array(full.astype(np.int32)), pa.array([salt] * len(full), pa.int32()), pa.array([rows[k].tobytes() for k in full])], ["block", "salt", "counts"])

    def add(pdf: pd.DataFrame) -> pd.DataFrame:
        total = np.zeros(4096, np.int64)
        for x in pdf["counts"]:
            total += np.frombuffer(x, np.int64)
        return pd.DataFrame({"block": pdf["block"][:1], "counts": [total.tobytes()]})

    parts = train.where(F.col(label).isNotNull() & F.col(text).isNotNull()).select(F.col(text), F.col(label)).mapInArrow(count, "block int, salt int, counts binary")
    parts = parts.groupBy("block", "salt").applyInPandas(add, "block int, counts binary").groupBy("block").applyInPandas(add, "block int, counts binary")
    counts = np.zeros((len(langs) * BUCKETS // 4096, 4096))
    for r in parts.collect():  # languages * BUCKETS numbers at most
        counts[r.block] = np.frombuffer(r.counts, np.int64)
    counts = counts.reshape(len(langs), BUCKETS)
    model = np.log((counts + 0.1) / (counts.sum(1, keepdims=True) + 0.1 * BUCKETS))
    prior = np.array([n for _, n in named], float)
    return langs, np.concatenate([model, np.log(prior / prior.sum())[:, None]], 1)


def predict(docs: DataFrame, model: tuple[list[str], np.ndarray], text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """keep columns of docs, then lang_pred and score."""
    langs, logp = model
    keep = docs.columns if keep is None else keep
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(logp)

    def score(batches):
        table_, prior = shared.value[:, :-1], shared.value[:, -1]
        tabs = [np.ascontiguousarray(x) for x in table_]
        for batch in batches:
            texts = batch.column(at).to_pylist()
            names, probs = [], []
            for i, j in pieces(texts):
                g, doc = grams(texts[i:j])
                like = np.zeros((j - i, len(langs)))
                seen = np.bincount(doc, minlength=j - i)
                if len(doc) and langs:
                    cut = np.flatnonzero(np.diff(doc, prepend=-1))
                    flat = g.ravel()
                    for k, t in enumerate(tabs):
                        like[doc[cut], k] = np.add.reduceat(t[flat], cut * 3)
                    like += prior
                    best = like.argmax(1)
                    p = 1 / np.exp(like - like.max(1, keepdims=True)).sum(1)
                for d in range(j - i):
                    ok = bool(seen[d]) and bool(langs)
                    names.append(langs[best[d]] if ok else "und")
                    probs.append(float(p[d]) if ok else 0.0)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(keep)], pa.array(names, pa.string()), pa.array(probs, pa.float64())], [*keep, "lang_pred", "score"])

    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep) + ", lang_pred string, score double"
    at = keep.index(text) if text in keep else len(keep)
    return docs.select(*[F.col(f"`{c}`") for c in keep], *[F.col(text).alias("__text")] * (text not in keep)).mapInArrow(score, schema)


def fold(doc_id: str, n: int):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % n


def op9(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang").withColumn("held_out", F.coalesce(fold("doc_id", 5) == 0, F.lit(False)))
    model = learn(docs.where(~F.col("held_out")))
    return predict(docs, model, keep=["doc_id", "held_out"])
