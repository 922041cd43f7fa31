"""The baselines the methods are compared with."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.losses import value_and_slope
from ..operators.vertex import VertexGraph, VertexProgram, run_vertex
from ..runtime import RunReport, forget, keyed_version, version
from ..sources.tables import vertices
from ..tasks.learning import bgd


def inmem_bgd(train: DataFrame, features: list[str], **options) -> tuple[list[float], RunReport, list]:
    """Records cached in memory only, one layer of sqrt(P) pre-aggregators. Records that don't fit are read again each round."""
    kept = train.persist(StorageLevel.MEMORY_ONLY)
    try:
        return bgd(kept, features, topology="sqrt", **options)
    finally:
        kept.unpersist()


def two_job_rank(edges: DataFrame, damping: float = 0.85, iterations: int = 10) -> DataFrame:
    """Each round is two jobs with files between: ranks are joined with the whole graph (both shuffled, nothing kept), then contributions are grouped."""
    ids = vertices(edges)
    n = max(ids.count(), 1)
    graph = ids.join(edges.groupBy("src").agg(F.collect_list("dst").alias("out")), F.col("id") == F.col("src"), "left").select("id", F.coalesce("out", F.array().cast(f"array<{edges.schema['dst'].dataType.simpleString()}>")).alias("out"))
    rank = version(ids.withColumn("rank", F.lit(1.0 / n)), "rank")
    graph = version(graph, "graph")
    for _ in range(iterations):
        joined = graph.hint("merge").join(rank, "id")
        sent = joined.select(F.explode("out").alias("id"), F.try_divide("rank", F.size("out").cast("double")).alias("c")).unionByName(joined.select("id", F.lit(0.0).alias("c")))
        sent = version(sent, "contributions")
        rank = version(sent.groupBy("id").agg((F.lit((1 - damping) / n) + F.lit(damping) * F.sum("c")).alias("rank")), "rank")
    return rank


def bgd_as_vertices(records: DataFrame, features: list[str], loss: str = "squared", eta: float = 0.5, iterations: int = 5, key: str = "id") -> list[float]:
    """A global model forced into vertices: d feature vertices (ids -1 to -d) hold a weight each, every record is a vertex that holds its slope.

    An iteration is two supersteps over edges weighted by the record's feature values: weights times values add up to a record's prediction, then slopes times
    values add up to a feature's gradient. All N d products are made in each, combined by destination. Features are hubs: their weights are broadcast, and
    records, their edges and states stay in the same buckets. Ids of records are unique and not negative; they are read once."""
    spark = records.sparkSession
    kept = keyed_version(records.select(F.col(key).cast("long").alias("id"), F.col("y").cast("double").alias("y"), *[F.col(f).cast("double").alias(f"f{k}") for k, f in enumerate(features)]), "records", "id", int(spark.conf.get("spark.sql.shuffle.partitions")))
    n = max(kept.count(), 1)
    cells = kept.select("id", F.posexplode(F.array(*[F.col(f"f{k}") for k in range(len(features))])).alias("k", "weight"))
    cells = cells.select("id", (-1 - F.col("k")).cast("long").alias("feature"), "weight")
    edges, hub_edges = (cells.select(F.col(a).alias("src"), F.col(b).alias("dst"), "weight") for a, b in (("id", "feature"), ("feature", "id")))
    hubs = spark.range(len(features)).select((-1 - F.col("id")).alias("id"), F.lit(None).cast("double").alias("y"), F.lit(True).alias("hub"))
    everyone = kept.select("id", "y", F.lit(False).alias("hub")).unionByName(hubs)
    at = F.col("state")
    moved = F.when(at.hub, at.v - F.lit(eta) * F.col("inbox") / n).otherwise(value_and_slope(loss, F.col("inbox"), at.y)[1])
    program = VertexProgram(
        init=lambda: F.struct("y", F.lit(0.0).alias("v"), "hub"),
        emit=lambda: at.v * F.col("weight"),
        update=lambda: F.struct(at.y.alias("y"), moved.alias("v"), at.hub.alias("hub")),
        send_if=lambda: at.hub == (F.col("step") % 2 == 0),
    )
    state, _ = run_vertex(program, VertexGraph(everyone, edges, [-1 - k for k in range(len(features))], hub_edges), 2 * iterations)
    forget(kept)
    weights = {r.id: r.v for r in state.where("state.hub").select("id", "state.v").collect()}  # one row a feature
    return [weights[-1 - k] for k in range(len(features))]


def keyed_statistic(df: DataFrame, column: str) -> DataFrame:
    """A global sum with a superfluous key: all values are shuffled to one group, nothing is combined before."""
    rows = df.select(F.lit(0).alias("k"), F.col(column).alias("v")).repartition("k")
    return rows.groupBy("k").agg(F.collect_list("v").alias("all")).select(F.aggregate("all", F.lit(0).cast(df.schema[column].dataType), lambda s, x: s + x).alias("sum"))


def rank_on_mru(edges: DataFrame, damping: float = 0.85, iterations: int = 10) -> dict:
    """A local model forced into a global one: all ranks are the model and go to every task. For small graphs (the model is checked)."""
    ids = [r.id for r in vertices(edges).limit(10_001).collect()]
    if len(ids) > 10_000:
        raise ValueError("the model would hold more than 10,000 ranks")
    out = edges.groupBy("src").agg(F.count("*").alias("deg"))
    e = edges.join(out, "src").persist()
    rank = {i: 1.0 / len(ids) for i in ids}
    for _ in range(iterations):
        model = F.broadcast(e.sparkSession.createDataFrame(list(rank.items()), ["src", "rank"]))
        sums = {r.dst: r.s for r in e.join(model, "src").groupBy("dst").agg(F.sum(F.col("rank") / F.col("deg")).alias("s")).collect()}
        rank = {i: (1 - damping) / len(ids) + damping * sums.get(i, 0.0) for i in ids}
    e.unpersist()
    return rank


def statistic_on_vertices(df: DataFrame, column: str) -> int:
    """A global sum as a vertex program: each record's vertex sends its value to vertex -1."""
    rows = df.select(F.monotonically_increasing_id().alias("id"), F.col(column).cast("long").alias("v"))
    rows = version(rows, "records")
    hub = df.sparkSession.createDataFrame([(-1, 0)], "id long, v long")
    program = VertexProgram(init=lambda: F.col("v"), emit=lambda: F.col("state"), update=lambda: F.col("inbox"), combine="sum")
    state, _ = run_vertex(program, VertexGraph(rows.unionByName(hub), rows.select(F.col("id").alias("src"), F.lit(-1).cast("long").alias("dst"))), 1)
    return state.where("id = -1").first().state
