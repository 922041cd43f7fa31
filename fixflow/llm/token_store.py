"""Token ids as binary shard files with constant-time keyed access.

A shard is one file: ids of its documents in ascending key order as little-endian unsigned integers (two bytes each
where every id of the vocabulary fits, else four), then an index: a minimal perfect hash of the document keys (levels of
bit arrays; keys that collide go to the next level; the rank of a key's bit is its slot), and for every slot a stored
fingerprint, the offset and the length. A lookup reads one bit, one rank, one fingerprint and one slice. The file ends
with a JSON footer and its length.

Shards are ranges of the key, so their order is the order of the documents; a task writes under a name of its own attempt
and reports it, and only reported files count, so lost or repeated tasks do no harm. Files lie in the folder
that all executors share.

Nulls: a null text has the end id alone; null keys come first. Rows that share a key are numbered within it in order of
their text. An empty table gives no rows.
"""

from __future__ import annotations

import json
import zlib
from uuid import uuid4

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bpe
from .common import new_path, ship, table, width

MASK = np.uint64(0xFFFFFFFFFFFFFFFF)


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    x = x ^ np.uint64((salt * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def hashed_keys(keys: pd.Series) -> np.ndarray:
    """64-bit key of each row: the key and its number among equal keys (keys stand together)."""
    null = keys.isna().to_numpy()
    plain = keys.fillna(0).astype("int64").to_numpy().view(np.uint64)
    nth = keys.fillna(0).astype("int64").groupby([null, plain]).cumcount().to_numpy().astype(np.uint64) + null * np.uint64(1 << 62)
    return mix(plain) ^ np.where(nth == 0, np.uint64(0), mix(nth, 7))


class PerfectHash:
    """Minimal perfect hash of distinct 64-bit keys."""

    def __init__(self, levels: list[np.ndarray]):
        self.levels = levels  # bits, packed
        self.bits = [np.unpackbits(x) for x in levels]
        self.rank, base = [], 0
        for b in self.bits:
            self.rank.append(base + np.cumsum(b) - b)
            base += int(b.sum())
        self.n = base

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        levels = []
        while len(keys):
            if len(levels) > 200:
                raise ValueError("keys are not distinct")
            m = max(64, -(-len(keys) * 3 // 2 // 8) * 8)
            at = (mix(keys, len(levels) + 1) % np.uint64(m)).astype(np.int64)
            alone = np.bincount(at, minlength=m) == 1
            levels.append(np.packbits(alone))
            keys = keys[~alone[at]]
        return cls(levels)

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        """The slot of each key, or -1 where no level has its bit."""
        out = np.full(len(keys), -1, np.int64)
        todo = np.arange(len(keys))
        for k, (bits, rank) in enumerate(zip(self.bits, self.rank)):
            at = (mix(keys[todo], k + 1) % np.uint64(len(bits))).astype(np.int64)
            hit = bits[at] == 1
            out[todo[hit]] = rank[at[hit]]
            todo = todo[~hit]
        return out


def file_system(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_store(docs: DataFrame, path: str, end_id: int = 1, shards: int | None = None, doc_id: str = "doc_id", text: str = "text", out_uri: str | None = None) -> tuple[str, list[dict]]:
    """Encode, append end_id and write. Returns the folder and the manifest (a row for each shard file)."""
    spark = docs.sparkSession
    ship(spark)
    uri = out_uri or new_path(spark, "tokens")

    def write(batches):
        from pyspark import TaskContext

        store = bpe.load(path)
        kind = np.dtype("<u2") if store.size <= 1 << 16 and end_id < 1 << 16 else np.dtype("<u4")
        end = np.array([end_id], kind).tobytes()
        fs, folder = file_system(uri)
        fs.create_dir(folder, recursive=True)
        shard = TaskContext.get().partitionId()
        name = f"shard-{shard:06d}-{uuid4().hex}.ids"
        keys, lens, out = [], [], None

        def make(ids, at):
            raw = ids.astype(kind).tobytes()
            return [raw[i * kind.itemsize : j * kind.itemsize] for i, j in zip(at, at[1:])]

        for b in batches:
            if out is None:
                out = fs.open_output_stream(f"{folder}/{name}")
            keys.append(b.column(0).to_pandas())
            for chunk in bpe.groups(b.column(1).cast(pa.binary()).to_pylist()):
                got = store.remember(f"bytes{kind.itemsize}", chunk, make)
                for c in chunk:
                    raw = b"".join(map(got.__getitem__, c)) + end
                    lens.append(len(raw) // kind.itemsize)
                    out.write(raw)
        if out is None or not lens:
            return
        key = pd.concat(keys, ignore_index=True)
        hashed = hashed_keys(key)
        index = PerfectHash.build(hashed)
        slot = index(hashed)
        n = np.array(lens, np.int64)
        at = np.cumsum(n) - n
        cols = {"finger": mix(hashed, 99).astype("<u4"), "start": at.astype("<i8"), "n": n.astype("<i8")}
        foot = {"width": kind.itemsize, "ids": int(n.sum()), "docs": len(n), "levels": [len(x) for x in index.levels]}
        for x in index.levels:
            out.write(x.tobytes())
        for c in cols.values():
            placed = np.empty_like(c)
            placed[slot] = c
            out.write(placed.tobytes())
        tail = json.dumps(foot).encode()
        out.write(tail + len(tail).to_bytes(4, "little"))
        out.close()
        known = key.dropna()
        low, high = (None, None) if known.empty else (int(known.min()), int(known.max()))
        yield pa.RecordBatch.from_pylist([{"shard": shard, "file": name, "docs": len(n), "ids": int(n.sum()), "low": low, "high": high, "nulls": bool(len(known) < len(key))}], pa.schema([("shard", pa.int32()), ("file", pa.string()), ("docs", pa.int64()), ("ids", pa.int64()), ("low", pa.int64()), ("high", pa.int64()), ("nulls", pa.bool_())]))

    ranged = docs.select(F.col(doc_id).cast("long").alias("k"), F.col(text).alias("t")).repartitionByRange(shards or width(spark), F.col("k").asc_nulls_first()).sortWithinPartitions(F.col("k").asc_nulls_first(), "t")
    manifest = ranged.mapInArrow(write, "shard int, file string, docs long, ids long, low long, high long, nulls boolean").collect()  # a row for each shard
    start, rows = 0, []
    for m in sorted(manifest, key=lambda m: m.shard):
        rows.append(m.asDict() | {"start": start})
        start += m.ids
    return uri, rows


class Shard:
    """Reader of one shard file."""

    def __init__(self, uri: str, name: str):
        fs, folder = file_system(uri)
        with fs.open_input_file(f"{folder}/{name}") as f:
            self.raw = memoryview(f.readall())
        size = int.from_bytes(self.raw[-4:], "little")
        foot = json.loads(bytes(self.raw[-4 - size : -4]))
        self.kind = np.dtype(f"<u{foot['width']}")
        self.payload = np.frombuffer(self.raw, self.kind, foot["ids"])
        at = foot["ids"] * foot["width"]
        levels = []
        for n in foot["levels"]:
            levels.append(np.frombuffer(self.raw, np.uint8, n, at))
            at += n
        self.index = PerfectHash(levels)
        self.finger = np.frombuffer(self.raw, "<u4", foot["docs"], at)
        self.start = np.frombuffer(self.raw, "<i8", foot["docs"], at + 4 * foot["docs"])
        self.n = np.frombuffer(self.raw, "<i8", foot["docs"], at + 12 * foot["docs"])

    def slots(self, hashed: np.ndarray) -> np.ndarray:
        """Slot of each key, -1 for keys that the shard doesn't hold."""
        s = self.index(hashed)
        good = s >= 0
        good[good] = self.finger[s[good]] == mix(hashed[good], 99).astype("<u4")
        return np.where(good, s, -1)

    def ids(self, slot: int) -> np.ndarray:
        return self.payload[self.start[slot] : self.start[slot] + self.n[slot]]


def look_up(keys: DataFrame, uri: str, manifest: list[dict], doc_id: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids) of keys, read from the files; keys not held are left out."""
    lows = [(m["low"], m["high"], m["shard"]) for m in manifest if m["low"] is not None]
    bounds, shard_of = np.array([x[1] for x in lows], np.int64), np.array([x[2] for x in lows], np.int32)
    nulls = next((m["shard"] for m in manifest if m["nulls"]), -1)
    by_shard = {m["shard"]: m for m in manifest}

    def route(batches):
        for b in batches:
            k = b.column(0).to_pandas()
            v = k.fillna(0).astype("int64").to_numpy()
            at = np.searchsorted(bounds, v)
            s = np.where(at < len(bounds), shard_of[np.minimum(at, max(0, len(bounds) - 1))] if len(bounds) else -1, -1)
            s = np.where(k.isna().to_numpy(), nulls, s).astype(np.int32)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s)], ["doc_id", "shard"])

    def read(pdf: pd.DataFrame) -> pd.DataFrame:
        m = by_shard.get(int(pdf["shard"].iloc[0]))
        cols = ["doc_id", "start", "n_tokens", "ids_crc32"] + ["ids"] * with_ids
        if m is None:
            return pd.DataFrame({c: [] for c in cols})
        shard = Shard(uri, m["file"])
        k = pdf["doc_id"].sort_values(kind="stable", na_position="first").reset_index(drop=True)
        slots = shard.slots(hashed_keys(k))
        k, slots = k[slots >= 0], slots[slots >= 0]
        crc = [zlib.crc32(shard.ids(s).astype("<u4").tobytes()) for s in slots]
        out = {"doc_id": k.astype("Int64"), "start": m["start"] + shard.start[slots], "n_tokens": shard.n[slots], "ids_crc32": np.array(crc, np.int64)}
        return pd.DataFrame(out | ({"ids": [shard.ids(s).astype(np.int64) for s in slots]} if with_ids else {}))

    if not manifest:
        return keys.sparkSession.createDataFrame([], "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids)
    routed = keys.select(F.col(doc_id).cast("long").alias("doc_id")).mapInArrow(route, "doc_id long, shard int")
    return routed.groupBy("shard").applyInPandas(read, "doc_id long, start long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids)


def op10(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    uri, manifest = write_store(docs, bpe.vocabulary())
    return look_up(docs, uri, manifest)
