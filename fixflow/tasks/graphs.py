"""Graph tasks as vertex programs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from ..operators.vertex import VertexGraph, VertexProgram, deliver, run_vertex
from ..runtime import RunReport, release, version
from ..sources.tables import vertices


def pagerank(edges: DataFrame, damping: float = 0.85, iterations: int = 10, dangling: str = "drop", **options) -> tuple[DataFrame, RunReport]:
    """(id, rank): every vertex stays active for a fixed number of rounds; rank starts at 1/V.

    dangling: what sinks do with their rank: `drop` it, `redistribute` it over all vertices, or keep it by a `self` edge. Edge weights, if given, split a rank.
    Any option of `run_vertex` (exchange, store, early_grouping, join, truncation) runs it superstep by superstep there.
    """
    ids = vertices(edges)
    n = ids.count()
    if dangling == "self":
        sinks = ids.join(edges.select(F.col("src").alias("id")).distinct(), "id", "left_anti")
        loops = sinks.select(F.col("id").alias("src"), F.col("id").alias("dst"))
        edges = edges.unionByName(loops.withColumn("weight", F.lit(1)) if "weight" in edges.columns else loops)
    if dangling == "redistribute":
        return _redistributing(edges, ids, n, damping, iterations), RunReport()
    if not options:  # all vertices run in all rounds, so the supersteps are one lazy plan
        return pagerank_dense(edges, damping, iterations), RunReport()
    return pagerank_supersteps(edges, damping, iterations, **options)


def pagerank_supersteps(edges: DataFrame, damping: float = 0.85, iterations: int = 10, **options) -> tuple[DataFrame, RunReport]:
    """The same superstep by superstep, with a report of each, and any state store."""
    ids = vertices(edges)
    n = ids.count()
    program = VertexProgram(
        init=lambda: F.lit(1.0 / max(n, 1)),
        emit=lambda: F.col("state") * F.col("weight") / F.col("strength"),
        update=lambda: F.lit((1 - damping) / max(n, 1)) + F.lit(damping) * F.coalesce("inbox", F.lit(0.0)),
        combine="sum",
        stay=lambda: F.lit(True),
    )
    state, report = run_vertex(program, VertexGraph(ids, edges), iterations, **options)
    return state.select("id", F.col("state").alias("rank")), report


def _redistributing(edges: DataFrame, ids: DataFrame, n: int, damping: float, iterations: int) -> DataFrame:
    g = VertexGraph(ids, edges).prepared()
    out = g.edges.select("src", "degree").distinct()
    rank = ids.withColumn("rank", F.lit(1.0 / n))
    for j in range(iterations):
        sums = g.edges.join(rank, F.col("src") == F.col("id")).select("dst", (F.col("rank") * F.col("weight") / F.col("strength")).alias("c")).groupBy("dst").agg(F.sum("c").alias("s"))
        lost = rank.join(out, F.col("id") == F.col("src"), "left_anti").agg(F.coalesce(F.sum("rank"), F.lit(0.0)).alias("lost"))
        rank = version(ids.join(sums, F.col("id") == F.col("dst"), "left").join(F.broadcast(lost)).select("id", (F.lit((1 - damping) / n) + F.lit(damping) * (F.coalesce("s", F.lit(0.0)) + F.col("lost") / n)).alias("rank")), "rank")
    return rank


def pagerank_dense(edges: DataFrame, damping: float = 0.85, iterations: int = 10, exchange: str = "hash_agg", early: bool = True) -> DataFrame:
    """The fixed number of rounds as one lazy plan: each round shuffles combined contributions only, and refers to the ranks once, so the plan grows linearly."""
    g = VertexGraph(vertices(edges), edges).prepared()
    n = g.vertices.count()
    base = g.vertices.select(F.col("id").alias("dst"), F.lit(0.0).alias("c"))
    rank = g.vertices.withColumn("rank", F.lit(1.0 / max(n, 1)))
    for _ in range(iterations):
        sent = g.edges.join(rank, F.col("src") == F.col("id")).select("dst", (F.col("rank") * F.col("weight") / F.col("strength")).alias("c"))
        sums = deliver(sent.unionByName(base).withColumnRenamed("c", "payload"), "sum", exchange, early)
        rank = sums.select(F.col("dst").alias("id"), (F.lit((1 - damping) / max(n, 1)) + F.lit(damping) * F.col("inbox")).alias("rank"))
    return rank


def pagerank_delta(edges: DataFrame, damping: float = 0.85, iterations: int = 10, tol: float = 0.0) -> tuple[DataFrame, RunReport]:
    """(id, rank): a vertex sends the change of its contribution, and only if its rank moved by more than tol; the state keeps the sum received."""
    ids = vertices(edges)
    n = max(ids.count(), 1)
    base = (1 - damping) / n
    rank = lambda c: F.lit(base) + F.lit(damping) * c.getField("got")
    program = VertexProgram(
        init=lambda: F.struct(F.lit((1.0 / n - base) / damping).alias("got"), F.lit(0.0).alias("told"), F.lit(True).alias("first")),
        # in the first round neighbours replace what they start with by what they are sent
        emit=lambda: (rank(F.col("state")) - F.col("state.told")) * F.col("weight") / F.col("strength"),
        update=lambda: F.struct(
            F.when(F.col("state.first"), F.coalesce("inbox", F.lit(0.0))).otherwise(F.col("state.got") + F.coalesce("inbox", F.lit(0.0))).alias("got"),
            F.when(F.abs(rank(F.col("state")) - F.col("state.told")) > tol, rank(F.col("state"))).otherwise(F.col("state.told")).alias("told"),
            F.lit(False).alias("first"),
        ),
        combine="sum",
        send_if=lambda: F.abs(rank(F.col("state")) - F.col("state.told")) > tol,
        stay=lambda: F.col("state.first") | (F.abs(rank(F.col("state")) - F.col("state.told")) > tol),
    )
    state, report = run_vertex(program, VertexGraph(ids, edges), iterations)
    return state.select("id", rank(F.col("state")).alias("rank")), report


UNIT = 10**12


def pagerank_exact(edges: DataFrame, iterations: int = 10) -> DataFrame:
    """Ranks in whole units of 1e-12 with integer division: the same in every engine and order."""
    ids = vertices(edges)
    n = max(ids.count(), 1)
    program = VertexProgram(
        init=lambda: F.lit(UNIT // n).cast("long"),
        emit=lambda: F.expr("state div degree"),
        update=lambda: F.lit(15 * UNIT // 100 // n).cast("long") + F.expr("(85 * coalesce(inbox, 0L)) div 100"),
        combine="sum",
        stay=lambda: F.lit(True),
    )
    state, _ = run_vertex(program, VertexGraph(ids, edges), iterations)
    return state.select("id", F.col("state").alias("rank"))


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def connected_components(edges: DataFrame, max_supersteps: int = 1000) -> tuple[DataFrame, RunReport]:
    """(id, component): the smallest id that a vertex is connected with; only vertices whose label fell send."""
    program = VertexProgram(
        init=lambda: F.col("id"),
        emit=lambda: F.col("state"),
        update=lambda: F.when(F.col("inbox") < F.col("state"), F.col("inbox")),
        combine="min",
        send_if=lambda: F.col("old").isNull() | (F.col("state") < F.col("old")),
    )
    state, report = run_vertex(program, VertexGraph(vertices(edges), both_ways(edges)), max_supersteps, to_fixpoint=True)
    return state.select("id", F.col("state").alias("component")), report


def sssp(edges: DataFrame, sources: DataFrame, max_supersteps: int = 1000, weighted: bool = False) -> tuple[DataFrame, RunReport]:
    """(id, distance): least number of edges (or weight) from any of sources (id); null where not reachable."""
    ids = vertices(edges).join(sources.select("id").distinct().withColumn("start", F.lit(True)), "id", "left")
    far = F.col("state").isNotNull() & (F.col("old").isNull() | (F.col("state") < F.col("old")))
    program = VertexProgram(
        init=lambda: F.when(F.col("start"), F.lit(0).cast("long")),
        emit=lambda: F.col("state") + (F.col("weight") if weighted else F.lit(1).cast("long")),
        update=lambda: F.when(F.col("state").isNull() | (F.col("inbox") < F.col("state")), F.col("inbox")),
        combine="min",
        send_if=lambda: far,
    )
    state, report = run_vertex(program, VertexGraph(ids, edges), max_supersteps, to_fixpoint=True)
    return state.select("id", F.col("state").alias("distance")), report


def label_propagation(edges: DataFrame, rounds: int) -> DataFrame:
    """(id, label): each round takes the label of largest weight among in-neighbours, the smallest on ties."""
    e = edges if "weight" in edges.columns else edges.withColumn("weight", F.lit(1).cast("long"))
    label = vertices(edges).withColumn("label", F.col("id"))
    for _ in range(rounds):
        votes = e.join(label, F.col("src") == F.col("id")).groupBy("dst", F.col("label").alias("l")).agg(F.sum("weight").alias("w"))
        best = votes.groupBy("dst").agg(F.max("w").alias("w")).join(votes, ["dst", "w"]).groupBy("dst").agg(F.min("l").alias("l"))
        label = version(label.join(best, F.col("id") == F.col("dst"), "left").select("id", F.coalesce("l", "label").alias("label")), "label")
    return label


def degree_stats(edges: DataFrame) -> DataFrame:
    out = edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("out_degree"))
    back = edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("in_degree"))
    zero = F.lit(0).cast("long")
    return out.join(back, "id", "full").select("id", F.coalesce("out_degree", zero).alias("out_degree"), F.coalesce("in_degree", zero).alias("in_degree"))


DEGREES_BROADCAST = 1 << 22  # vertices, 24 bytes each and more


def triangle_count(edges: DataFrame, block: int = 1 << 19) -> DataFrame:
    """(id, triangles): edges point from lower to higher degree, so no vertex has more than sqrt(2E) out-edges.

    Wedges never leave a task: sources are cut into ranges of about `block` edges; each range gets the out-edges of the vertices it points to, once each,
    and looks up which of them close a triangle. Ids that are no integers are numbered for that."""
    spark = edges.sparkSession
    if not isinstance(edges.schema["src"].dataType, IntegralType):
        number = version(vertices(edges.where("src <> dst")).withColumn("n", F.monotonically_increasing_id()), "numbers")
        for c in ("src", "dst"):
            edges = edges.join(number.select(F.col("id").alias(c), F.col("n").alias(f"{c}_n")), c)
        counts = triangle_count(edges.select(F.col("src_n").alias("src"), F.col("dst_n").alias("dst")), block).withColumnRenamed("id", "n")
        return counts.join(number, "n").select("id", "triangles")
    pairs = version(edges.where("src <> dst").select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst")).distinct(), "pairs")
    release(spark)
    deg = version(pairs.select(F.explode(F.array("src", "dst")).alias("id")).groupBy("id").agg(F.count("*").alias("d")), "degrees")
    near = F.broadcast if deg.count() <= DEGREES_BROADCAST else lambda df: df
    both = pairs.join(near(deg.select(F.col("id").alias("src"), F.col("d").alias("d1"))), "src").join(near(deg.select(F.col("id").alias("dst"), F.col("d").alias("d2"))), "dst")
    up = F.struct("d1", "src") < F.struct("d2", "dst")
    e = version(both.select(F.when(up, F.col("src")).otherwise(F.col("dst")).alias("src"), F.when(up, F.col("dst")).otherwise(F.col("src")).alias("dst")), "oriented")
    release(spark)
    ranges = max(1, -(-e.count() // block))
    cuts = e.approxQuantile("src", [k / ranges for k in range(1, ranges)], 1 / (4 * ranges)) if ranges > 1 else []

    def dealt(batches):
        import numpy as np
        import pyarrow as pa

        for b in batches:
            at = np.searchsorted(np.asarray(cuts, dtype="f8"), b.column(0).to_numpy(zero_copy_only=False), side="right")
            yield pa.RecordBatch.from_arrays([pa.array(at.astype("i4")), *b.columns], names=["block", "src", "dst"])

    def closed(near, far):
        import numpy as np
        import pyarrow as pa

        src, dst, via, third = (t[c].to_numpy() for t, c in ((near, "src"), (near, "dst"), (far, "via"), (far, "third")))
        us, ui = np.unique(src, return_inverse=True)
        ds, di = np.unique(dst, return_inverse=True)
        own = np.sort(ui * len(ds) + di)  # the range's edges
        ui, di = own // max(1, len(ds)), own % max(1, len(ds))
        known = np.isin(third, ds)
        at, end = np.searchsorted(ds, via[known]), np.searchsorted(ds, third[known])
        order = np.argsort(at, kind="stable")
        end, starts = end[order], np.searchsorted(at[order], np.arange(len(ds) + 1))
        many = np.diff(starts)[di]  # wedges of each edge
        total = np.cumsum(many)
        n_src, n_dst = np.zeros(len(us), "i8"), np.zeros(len(ds), "i8")
        lo = 0
        while lo < len(own):
            hi = max(lo + 1, int(np.searchsorted(total, total[lo] - many[lo] + (1 << 21), side="right")))
            m = many[lo:hi]
            edge = np.repeat(np.arange(lo, hi), m)
            w = end[np.repeat(starts[di[lo:hi]] - (np.cumsum(m) - m), m) + np.arange(len(edge))]
            probe = ui[edge] * len(ds) + w
            hit = own[np.minimum(np.searchsorted(own, probe), len(own) - 1)] == probe
            n_src += np.bincount(ui[edge[hit]], minlength=len(us))
            n_dst += np.bincount(di[edge[hit]], minlength=len(ds)) + np.bincount(w[hit], minlength=len(ds))
            lo = hi
        ids, n = np.concatenate([us, ds]), np.concatenate([n_src, n_dst])
        return pa.table({"id": pa.array(ids[n > 0], pa.int64()), "n": pa.array(n[n > 0], pa.int64())})

    near, same = (e.mapInArrow(dealt, "block int, src long, dst long") for _ in range(2))
    far = same.select("block", F.col("dst").alias("via")).distinct().join(e.select(F.col("src").alias("via"), F.col("dst").alias("third")), "via")
    found = near.groupBy("block").cogroup(far.select("block", "via", "third").groupBy("block")).applyInArrow(closed, "id long, n long")
    return found.groupBy("id").agg(F.sum("n").alias("triangles"))


def k_core(edges: DataFrame, k: int) -> DataFrame:
    """(id): vertices of the largest subgraph in which all degrees are at least k."""
    e = version(both_ways(edges).where("src <> dst"), "core")
    while True:
        ok = e.groupBy("src").count().where(F.col("count") >= k).select("src")
        nxt = version(e.join(ok, "src", "left_semi").join(ok.withColumnRenamed("src", "dst"), "dst", "left_semi").select("src", "dst"), "core")
        if nxt.count() == e.count():
            return nxt.select(F.col("src").alias("id")).distinct()
        e = nxt


def hits(edges: DataFrame, rounds: int = 10) -> DataFrame:
    """(id, hub, authority), each of unit length."""
    ids = vertices(edges)
    hub = ids.withColumn("hub", F.lit(1.0))
    norm = lambda df, c: df.join(F.broadcast(df.agg(F.sqrt(F.sum(F.col(c) * F.col(c))).alias("len")))).withColumn(c, F.try_divide(F.col(c), F.col("len"))).drop("len")
    for _ in range(rounds):
        auth = norm(ids.join(edges.join(hub, F.col("src") == F.col("id")).groupBy(F.col("dst").alias("id")).agg(F.sum("hub").alias("a")), "id", "left").select("id", F.coalesce("a", F.lit(0.0)).alias("authority")), "authority")
        auth = version(auth, "authority")
        hub = norm(ids.join(edges.join(auth, F.col("dst") == F.col("id")).groupBy(F.col("src").alias("id")).agg(F.sum("authority").alias("h")), "id", "left").select("id", F.coalesce("h", F.lit(0.0)).alias("hub")), "hub")
        hub = version(hub, "hub")
    return hub.join(auth, "id")


def personalized_pagerank(edges: DataFrame, sources: DataFrame, damping: float = 0.85, iterations: int = 10) -> DataFrame:
    """(id, rank): restarts go to the sources only."""
    n = max(sources.count(), 1)
    ids = vertices(edges).join(sources.select("id").withColumn("seed", F.lit(1.0 / n)), "id", "left").fillna(0.0, ["seed"])
    program = VertexProgram(
        init=lambda: F.struct(F.col("seed").alias("rank"), F.col("seed").alias("seed")),
        emit=lambda: F.col("state.rank") * F.col("weight") / F.col("strength"),
        update=lambda: F.struct((F.lit(1 - damping) * F.col("state.seed") + F.lit(damping) * F.coalesce("inbox", F.lit(0.0))).alias("rank"), F.col("state.seed").alias("seed")),
        stay=lambda: F.lit(True),
    )
    state, _ = run_vertex(program, VertexGraph(ids, edges), iterations)
    return state.select("id", F.col("state.rank").alias("rank"))
