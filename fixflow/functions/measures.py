"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def machine_seconds(machines: int, seconds: float) -> float:
    return machines * seconds


def cost_optimal(points: list[tuple[int, float]], tolerance: float = 0.01) -> int:
    """Fewest machines whose cost is within tolerance of the least. points: (machines, seconds)."""
    least = min(m * s for m, s in points)
    return min(m for m, s in points if m * s <= least * (1 + tolerance))


def cost_optimal_points(points: DataFrame, tolerance: float = 0.01) -> DataFrame:
    """(method, machines, least_cost): the same for each method of points (method, machines, seconds)."""
    cost = points.select("method", "machines", (F.col("machines") * F.col("seconds")).alias("cost"))
    least = cost.groupBy("method").agg(F.min("cost").alias("least_cost"))
    return cost.join(least, "method").where(F.col("cost") <= F.col("least_cost") * (1 + tolerance)).groupBy("method").agg(F.min("machines").alias("machines"), F.first("least_cost").alias("least_cost"))


def speedup(points: list[tuple[int, float]]) -> list[tuple[int, float, float]]:
    """(machines, speed-up over the smallest size, share of ideal)."""
    m0, s0 = min(points)
    return [(m, s0 / s, s0 * m0 / (s * m)) for m, s in sorted(points)]


def scaleup(points: list[tuple[float, float]]) -> list[tuple[float, float]]:
    """(data, time over that of the smallest data); 1 is ideal where machines grow with the data."""
    s0 = min(points)[1]
    return [(d, s / s0) for d, s in sorted(points)]


def compare(a: DataFrame, b: DataFrame, key: str, value: str) -> DataFrame:
    """l1 and linf between two keyed vectors; a missing key counts as 0."""
    both = a.select(key, F.col(value).alias("x")).join(b.select(key, F.col(value).alias("y")), key, "full")
    d = F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0)))
    return both.agg(F.coalesce(F.sum(d), F.lit(0.0)).alias("l1"), F.coalesce(F.max(d), F.lit(0.0)).alias("linf"))


def top_k_overlap(a: DataFrame, b: DataFrame, key: str, value: str, k: int) -> float:
    top = lambda df: df.orderBy(F.desc(value), key).limit(k).select(key)
    return top(a).join(top(b), key, "left_semi").count() / k


def plan_regret(chosen: float, times: dict[str, float]) -> float:
    """Time of the chosen plan over that of the best measured."""
    return chosen / min(times.values())


def shuffles(df: DataFrame) -> int:
    """Exchange nodes of the plan."""
    plan = df._jdf.queryExecution().sparkPlan().toString()
    planned = df._jdf.queryExecution().executedPlan().toString()
    return max(planned.split("== Initial Plan ==")[-1].count("Exchange "), plan.count("Exchange "))
