"""The iteration driver: a loop around DataFrames with durable cuts, stop rules and measures."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession

_own: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    if not _own:
        _own.append("file://" + tempfile.mkdtemp(prefix="fixflow-"))
    return _own[0]


def get_spark(master: str | None = None, **conf) -> SparkSession:
    b = SparkSession.builder.config("spark.sql.session.timeZone", "UTC")
    b = b.master(master) if master else b
    for k, v in conf.items():
        b = b.config(k, v)
    return b.getOrCreate()


def version(df: DataFrame, tag: str, at: str | None = None) -> DataFrame:
    """A durable version of df in the shared folder (or under `at`, where it stays): its lineage starts at files, which go when the driver's JVM ends."""
    path = f"{at or shared_dir(df.sparkSession)}/{tag}-{uuid.uuid4().hex}"
    if at is None:
        place = df.sparkSession.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(place)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def keyed_version(df: DataFrame, tag: str, key: str, width: int | None = None) -> DataFrame:
    """A durable version of df in `width` buckets of its key: joins and groups by the key need no exchange. Without a width, df is dealt by the key already.

    It is a table of the session until `forget` drops it; its files go then, or when the driver's JVM ends."""
    spark = df.sparkSession
    name, path = f"fixflow_{tag}_{uuid.uuid4().hex}", f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(place)
    buckets = width or int(spark.conf.get("spark.sql.shuffle.partitions"))
    df = df.repartition(buckets, key) if width else df
    df.write.bucketBy(buckets, key).sortBy(key).format("parquet").option("compression", "zstd").option("path", path).saveAsTable(name)
    out = spark.table(name)
    out._fixflow_table = (name, path)
    return out


def forget(df: DataFrame) -> None:
    """Drops a `keyed_version` and its files."""
    spark, (name, path) = df.sparkSession, df._fixflow_table
    spark.sql(f"drop table if exists {name}")
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def release(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete the shuffle files of results that are written and no longer referred to."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


@dataclass
class Truncation:
    """How states are kept between rounds: a durable `version` each, or `persist` in memory and on disk with a version every `every` rounds.

    A state that refers to the one before it twice doubles the plan with each round, so persisting alone suits few rounds."""

    every: int = 3
    form: str = "version"

    def keep(self, df: DataFrame, round_: int) -> DataFrame:
        if self.form == "version" or (self.every and round_ % self.every == 0 and round_):
            return version(df, "state")
        return df.persist(StorageLevel.MEMORY_AND_DISK)


@dataclass
class RunReport:
    """Measures of a run, a value for each round."""

    iteration_seconds: list[float] = field(default_factory=list)
    loss: list[float] = field(default_factory=list)
    delta: list[float] = field(default_factory=list)
    active: list[int] = field(default_factory=list)
    messages: list[int] = field(default_factory=list)

    def mean_seconds(self) -> float:
        return sum(self.iteration_seconds) / max(1, len(self.iteration_seconds))


class FixpointDriver:
    """init() -> state; step(round, state) -> (state, measures); stop(round, measures) -> bool.

    A state is a DataFrame (kept by `truncation`) or any driver value. Older DataFrames are released once the next one exists.
    """

    def __init__(self, init: Callable, step: Callable, stop: Callable, truncation: Truncation | None = None):
        self.init, self.step, self.stop, self.truncation = init, step, stop, truncation or Truncation()

    def run(self, report: RunReport | None = None):
        report = report or RunReport()
        state, j, alive = self.init(), 0, []
        while True:
            began = time.perf_counter()
            out = self.step(j, state)
            if out is None:
                break
            new, measures = out
            for k, v in measures.items():
                if hasattr(report, k):
                    getattr(report, k).append(v)
            report.iteration_seconds.append(time.perf_counter() - began)
            if isinstance(state, DataFrame) and state is not new:
                alive.append(state)
                if len(alive) > 1:
                    alive.pop(0).unpersist()
            state, j = new, j + 1
            if self.stop(j, measures):
                break
        return state, report
