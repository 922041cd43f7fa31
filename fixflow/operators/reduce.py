"""Reduce topologies: ways to add up statistics of all records. All give equal sums; they differ in who receives how much.

flat: all records meet in one task. early: one partial row a task. sqrt: a layer of about sqrt(P) pre-aggregators between. local_sqrt: tasks of a machine
join first, then that layer. tree: layers of fan-in k. random: pre-aggregators are chosen by a hash of the row (stable under retries). blocks: a
vector is cut in blocks that are reduced apart (reduce-scatter). sparse: one row for each component.
"""

from __future__ import annotations

import math
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOPOLOGIES = ("flat", "early", "sqrt", "local_sqrt", "tree", "random", "blocks", "sparse")
MERGE = {"sum": F.sum, "min": F.min, "max": F.max}


def reduce_columns(df: DataFrame, stats: dict[str, Column], topology: str = "early", how: dict[str, str] | None = None) -> dict[str, Any]:
    row = reduced(df, stats, topology, how).first()
    return {k: row[k] for k in stats}


def reduced(df: DataFrame, stats: dict[str, Column], topology: str = "early", how: dict[str, str] | None = None, fan_in: int = 4, local: int = 4) -> DataFrame:
    """One row with a column for each statistic."""
    how = how or {}
    f = {k: MERGE[how.get(k, "sum")] for k in stats}
    rows = df.select(*[c.alias(k) for k, c in stats.items()])
    agg = lambda d, *by: (d.groupBy(*by) if by else d).agg(*[f[k](k).alias(k) for k in stats])
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if topology == "early":
        return agg(rows)
    if topology == "flat":
        return agg(rows.repartition(1))
    if topology in ("sqrt", "local_sqrt"):
        if topology == "local_sqrt":
            parts = max(1, parts // local)
            rows = rows.coalesce(parts)
        mid = max(1, math.isqrt(parts - 1) + 1) if parts > 1 else 1
        return agg(agg(rows.withColumn("pre", F.pmod(F.spark_partition_id(), F.lit(mid))), "pre"))
    if topology == "tree":
        level = agg(rows.withColumn("slot", F.spark_partition_id()), "slot")
        width = parts
        while width > fan_in:
            level = agg(level.withColumn("slot", F.floor(F.pmod(F.col("slot"), F.lit(width)) / fan_in).cast("int")), "slot")
            width = -(-width // fan_in)
        return agg(level)
    if topology == "random":
        return agg(agg(rows.withColumn("pre", F.pmod(F.xxhash64(*stats), F.lit(max(1, math.isqrt(parts))))), "pre"))
    if topology in ("blocks", "sparse"):
        size = 1 if topology == "sparse" else max(1, math.isqrt(len(stats)))
        names = list(stats)
        blocks = [names[i : i + size] for i in range(0, len(names), size)]
        one = rows if how else agg(rows.withColumn("slot", F.spark_partition_id()), "slot")  # early rows, then cut
        piece = F.explode(F.array(*[F.struct(F.lit(b).alias("block"), F.array(*[F.col(n) for n in (blk + blk[:1] * (size - len(blk)))]).alias("v")) for b, blk in enumerate(blocks)])).alias("x")
        if len({rows.schema[n].dataType.simpleString() for n in names}) > 1:
            one = one.select(*[F.col(n).cast("double").alias(n) for n in names])
        cut = one.select(piece).select("x.*")
        kinds = {n: f[n] for n in names}
        summed = cut.groupBy("block").agg(*[(kinds[names[0]])(F.col("v")[i]).alias(f"s{i}") for i in range(size)])
        return summed.agg(*[F.max(F.when(F.col("block") == b, F.col(f"s{i}"))).alias(n) for b, blk in enumerate(blocks) for i, n in enumerate(blk)])
    raise ValueError(topology)
