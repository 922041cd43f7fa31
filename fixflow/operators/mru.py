"""Iterative map-reduce-update: a global model, statistics of all records under it, and its update until it stays the same."""

from __future__ import annotations

import json
from collections.abc import Callable
from dataclasses import dataclass
from typing import Any

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime import FixpointDriver, RunReport


@dataclass
class MRU:
    """map(model) gives a Column for each statistic of a record; they are added up (or reduced by the aggregate named in `reduce`); update(j, model,
    statistics) gives the next model. A model is a driver value (small) that enters the plan as literals, so the map stays in generated code."""

    init: Callable[[], Any]
    map: Callable[[Any], dict[str, Column]]
    update: Callable[[int, Any, dict[str, Any]], Any]
    reduce: dict[str, str] | None = None
    halt: Callable[[Any], bool] | None = None


def run_mru(mru: MRU, records: DataFrame, max_iterations: int, topology: str = "early", cache: bool = False, store: str | None = None, resume: bool = False) -> tuple[Any, RunReport, list]:
    """(last model, report, all models). Stops if the model stays equal, its halt test holds or after max_iterations.

    cache keeps the records (they are loop-invariant); it spills to disk where memory is short. store: a folder for a version of the model each round; resume
    goes on from the newest version there, its rounds counted in max_iterations."""
    from .reduce import reduce_columns

    records = records.persist() if cache else records
    if topology == "auto":
        topology = pick_topology(records.sparkSession, len(mru.map(mru.init())))
    models: list[Any] = []
    done, begin = (resume and store and resume_model(records.sparkSession, store)) or (0, None)

    def step(j: int, model: Any):
        j += done
        if not models:
            models.append(model)
        if mru.halt and mru.halt(model):
            return None
        stats = reduce_columns(records, mru.map(model), topology, mru.reduce)
        new = mru.update(j, model, stats)
        models.append(new)
        if store:
            save_model(records.sparkSession, store, j + 1, new)
        return new, {"loss": stats.get("loss"), "same": new == model}

    first = (lambda: begin) if done else mru.init
    model, report = FixpointDriver(first, step, lambda j, m: j + done >= max_iterations or m["same"]).run() if max_iterations > done else (first(), RunReport())
    return model, report, models or [model]


def pick_topology(spark: SparkSession, statistics: int, bandwidth: float = 125e6) -> str:
    """The topology the cost rules choose for sums of so many numbers, given the session's executors and task slots. `flat` and `early` differ in what a task
    sends, not in who receives, so `early` stands for both."""
    from ..plans.cost import choose_reduce

    context = spark.sparkContext
    machines = max(1, context._jsc.sc().getExecutorMemoryStatus().size() - 1)  # without the driver
    chosen = choose_reduce(max(machines, context.defaultParallelism), machines, 8.0 * statistics, bandwidth)
    return "early" if chosen == "flat" else chosen


def save_model(spark: SparkSession, folder: str, j: int, model: Any) -> None:
    spark.createDataFrame([(j, json.dumps(model))], "version int, model string").coalesce(1).write.mode("overwrite").parquet(f"{folder}/version={j:06d}")


def resume_model(spark: SparkSession, folder: str) -> tuple[int, Any] | None:
    """The newest stored (round, model)."""
    try:
        row = spark.read.parquet(folder).orderBy(F.desc("version")).select("version", "model").first()
    except Exception as e:  # no folder yet
        if "PATH_NOT_FOUND" in str(e):
            return None
        raise
    return (int(row.version), json.loads(row.model)) if row else None


def stat_query(df: DataFrame, column: str) -> DataFrame:
    """min, max, sum, count, mean and variance in one round."""
    c = F.col(column)
    return df.agg(F.min(c).alias("min"), F.max(c).alias("max"), F.sum(c).alias("sum"), F.count(c).alias("count"), F.avg(c).alias("mean"), F.var_samp(c).alias("var"))


def check_aggregate_laws(merge: Callable, samples: list, close: Callable = lambda a, b: a == b) -> list[str]:
    """Which of commutativity and associativity a merge function breaks on samples."""
    broken = set()
    for a in samples:
        for b in samples:
            if not close(merge(a, b), merge(b, a)):
                broken.add("commutative")
            for c in samples:
                if not close(merge(merge(a, b), c), merge(a, merge(b, c))):
                    broken.add("associative")
    return sorted(broken)
