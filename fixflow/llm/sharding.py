"""Consistent-hash ring with virtual nodes and bounded loads.

Groups (equal texts) hash to one of ``CELLS`` cells of a ring on which every shard owns ``VNODES`` points. A cell goes
to the first point clockwise whose shard still has room under ``(1 + slack) * total / shards`` bytes; a full shard is
passed over. Placement is decided on cell totals only (at most CELLS numbers reach the driver, whatever the input), so
it is the same at every size. A cell that would fill more than 1/256 of a shard is cut by the hash of the text into pieces, so groups
of equal texts stay whole. A group is cut, by document hash, only if it alone would fill more than 1/16 of a shard: a text that
makes up a third of all rows is spread over shards. There are at most 32 such groups a shard.

Nulls: a null text has size 1 and the crc of no bytes; a null doc_id hashes like a value. Repeated rows each get a slot.
An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable

CELLS = 1 << 16
VNODES = 128


def ring(shards: int, vnodes: int = VNODES) -> list[tuple[int, int]]:
    """(cell, shard) of every virtual node, in ring order."""
    at = lambda s, v: int.from_bytes(hashlib.md5(f"{s}/{v}".encode()).digest()[:8], "big") % CELLS
    return sorted((at(s, v), s) for s in range(shards) for v in range(vnodes))


def place(pieces: list[tuple[int, int, int, int]], shards: int, slack: float) -> list[tuple[int, int, int, int]]:
    """pieces: (cell, sub, rows, bytes). Returns (cell, sub, shard, first slot).

    Larger pieces are placed before smaller ones of the same ring (classes by powers of two), which leaves small pieces
    to level the ends; within a class the order is that of the ring.
    """
    points = ring(shards)
    cells = [c for c, _ in points]
    total = sum(p[3] for p in pieces)
    room = total * (1 + slack) / shards
    load, slots = [0] * shards, [0] * shards
    out = []
    for cell, sub, rows, size in sorted(pieces, key=lambda p: (-p[3].bit_length(), p[0], p[1])):
        start, tried, home = bisect_left(cells, cell), set(), -1
        for k in range(len(points)):
            s = points[(start + k) % len(points)][1]
            if s in tried:
                continue
            if load[s] + size <= room:
                home = s
                break
            tried.add(s)
            if len(tried) == shards:
                break
        if home < 0:  # no shard has room for the whole piece: the emptiest takes it
            home = min(range(shards), key=lambda s: (load[s], s))
        out.append((cell, sub, home, slots[home]))
        load[home] += size
        slots[home] += rows
    return out


def assign_shards(docs: DataFrame, shards: int = 8, slack: float = 0.0005, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, shard, slot: sizes near equal, equal texts together unless they overflow a shard."""
    spark = docs.sparkSession
    slim = durable(
        docs.select(
            F.col(doc_id).alias("doc_id"),
            (F.coalesce(F.octet_length(F.col(text)), F.lit(0)) + 1).cast("long").alias("size"),
            F.crc32(F.coalesce(F.col(text), F.lit("")).cast("binary")).alias("text_crc32"),
            F.xxhash64(F.col(text)).alias("group"),
            F.pmod(F.xxhash64(F.col(text)), F.lit(CELLS)).cast("int").alias("cell"),
        ),
        "ring",
    )
    cells = slim.groupBy("cell").agg(F.count("*").alias("n"), F.sum("size").alias("b")).collect()  # at most CELLS rows
    total = sum(r.b for r in cells)
    piece, whole = max(1, total // (shards * 256)), max(1, total // (shards * 16))
    cut = {r.cell: min(CELLS // 8, -(-r.b // piece)) for r in cells if r.b > piece and r.n > 1}  # fewer than 512 * shards cells
    pieces = [(r.cell, 0, r.n, r.b) for r in cells if r.cell not in cut]
    if cut:
        cuts = F.broadcast(spark.createDataFrame(sorted(cut.items()), "cell int, parts int"))
        in_cut = slim.join(cuts.where(F.col("parts") > 16), "cell", "left_semi") if any(p > 16 for p in cut.values()) else slim.where(F.lit(False))
        groups = in_cut.groupBy("cell", "group").agg(F.sum("size").alias("b"), F.count("*").alias("n")).where((F.col("b") > whole) & (F.col("n") > 1)).collect()  # fewer than 16 * shards rows
        hot = F.broadcast(spark.createDataFrame([(r.cell, r.group, min(CELLS // 8, -(-r.b // piece))) for r in groups], "cell int, group long, shares int"))
        by_text, by_row = F.pmod(F.xxhash64("group"), F.col("parts")), F.col("parts") + F.pmod(F.xxhash64("doc_id", F.lit("sub")), F.col("shares"))
        slim = slim.join(cuts, "cell", "left").join(hot, ["cell", "group"], "left").withColumn("sub", F.coalesce(by_row, by_text, F.lit(0)).cast("int")).drop("parts", "shares")
        more = slim.where(F.col("cell").isin(*cut) if len(cut) < 64 else F.lit(True)).groupBy("cell", "sub").agg(F.count("*").alias("n"), F.sum("size").alias("b"))
        pieces += [(r.cell, r.sub, r.n, r.b) for r in more.join(cuts, "cell", "left_semi").collect()]  # fewer than 1024 * shards rows and two for each cut
    else:
        slim = slim.withColumn("sub", F.lit(0))
    plan = spark.createDataFrame(place(pieces, shards, slack), "cell int, sub int, shard int, base long")
    from pyspark.sql import Window

    numbered = slim.withColumn("k", F.row_number().over(Window.partitionBy("cell", "sub").orderBy("doc_id", "text_crc32", "size")))
    return numbered.join(F.broadcast(plan), ["cell", "sub"]).select(
        "doc_id", "size", "text_crc32", "shard", (F.col("base") + F.col("k") - 1).alias("slot")
    )


def op6(spark, sf_dir: str) -> DataFrame:
    from .common import table

    out = assign_shards(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
