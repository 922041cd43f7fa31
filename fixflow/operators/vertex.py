"""Vertex programs: bulk-synchronous supersteps as one join with loop-invariant edges and one keyed aggregation.

A program gives the state of a vertex, the payload it sends along an edge, how payloads for one vertex combine, and the new state. All of them are
Column expressions, so a superstep is code Catalyst generates. Messages are a bag (equal payloads from two senders both count). A vertex runs
only if it has a message; messages to unknown ids are dropped; a null new state keeps the old one; a vertex that asks to stay active sends itself an
activation, which is neutral in `combine`.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..runtime import FixpointDriver, RunReport, Truncation, forget, keyed_version

COMBINE = {"sum": F.sum, "min": F.min, "max": F.max, "list": lambda c: F.sort_array(F.collect_list(c))}


@dataclass
class VertexProgram:
    """init(): state column of a vertex row. emit(): payload from columns state, degree, weight. update(): new state from columns state, inbox,
    step (null: keep). send_if: which vertices send, from columns state, old, step. stay: which vertices run next time even without mail.
    send: messages to any ids, an array of structs (dst, payload) from columns src (the own id), state, old, step; beside emit, or instead of it (emit None).
    aggregates: values over all states at the end of a superstep; in the next one they are the columns agg_<name> (null in the first).
    on_unknown: `drop` messages to unknown ids or `create` a vertex with a null state, whose update sees the mail."""

    init: Callable[[], Column]
    emit: Callable[[], Column] | None
    update: Callable[[], Column]
    combine: str | None = "sum"
    send_if: Callable[[], Column] | None = None
    stay: Callable[[], Column] | None = None
    undirected: bool = False
    send: Callable[[], Column] | None = None
    aggregates: dict[str, Callable[[], Column]] | None = None
    on_unknown: str = "drop"


@dataclass
class VertexGraph:
    """Vertices (id, ...) and edges (src, dst[, weight]). Edges stay partitioned and sorted by source for the whole run.

    hubs: ids of few vertices with very many out-edges, which are given in hub_edges (src, dst, weight) and never gathered by source: the hubs' mail is broadcast.
    Both kinds of edges are then taken as they are, without degree and strength, and states are kept in buckets of their id; edges in the same buckets
    (`edges` by source, `hub_edges` by target) meet them without an exchange."""

    vertices: DataFrame
    edges: DataFrame
    hubs: list | None = None
    hub_edges: DataFrame | None = None

    def prepared(self, partitions: int | None = None) -> VertexGraph:
        if self.hubs is not None:
            return self
        e = self.edges if "weight" in self.edges.columns else self.edges.withColumn("weight", F.lit(1))
        degree = e.groupBy("src").agg(F.count("*").alias("degree"), F.sum("weight").alias("strength"))
        e = e.join(degree, "src")
        n = partitions or int(e.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        return VertexGraph(self.vertices, e.repartition(n, "src").sortWithinPartitions("src").persist(StorageLevel.MEMORY_AND_DISK))


def combined_at_sender(messages: DataFrame, combine: str, most: int = 1 << 20) -> DataFrame:
    """Messages of a task combined by destination before any exchange; what was combined goes out whenever `most` destinations are held."""
    import pyarrow as pa

    def run(batches):
        held: list = []
        for batch in batches:
            held.append(pa.Table.from_batches([batch]))
            if sum(t.num_rows for t in held) >= most:
                held = [folded(held)]
                if held[0].num_rows >= most // 2:
                    yield from held.pop().to_batches()
        if held:
            yield from folded(held).to_batches()

    def folded(tables: list):
        out = pa.concat_tables(tables).group_by("dst").aggregate([("payload", combine)])
        return out.rename_columns(["payload" if c.startswith("payload") else c for c in out.column_names]).select(["dst", "payload"])

    slim = messages.select("dst", "payload")
    return slim.mapInArrow(run, slim.schema)


def deliver(messages: DataFrame, combine: str | None, exchange: str = "hash_agg", early: bool = True) -> DataFrame:
    """(dst, inbox): messages combined by destination.

    hash_agg: partial hash aggregates before the exchange, final ones after it. hash_sort: senders combine, a plain hash exchange, receivers sort and group.
    sorted: senders combine and sort what they send, receivers bring the senders' runs into order (Spark has no merging exchange, so they sort again) and group.
    All three have a single exchange of combined messages. early=False, a baseline: nothing is combined before the exchange and a receiver holds all
    messages of a destination, so a vertex with more in-links than a task's memory holds ends the run.
    """
    f = COMBINE[combine or "list"]
    n = int(messages.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if combine in (None, "list"):
        return messages.groupBy("dst").agg(f("payload").alias("inbox"))
    if not early:  # whole groups arrive, then one fold over each
        whole = messages.groupBy("dst").agg(F.collect_list("payload").alias("all"))
        fold = {"sum": lambda a, x: a + x, "min": lambda a, x: F.least(a, x), "max": lambda a, x: F.greatest(a, x)}[combine]
        rest = F.slice("all", 2, F.greatest(F.size("all") - 1, F.lit(0)))
        return whole.select("dst", F.when(F.size("all") > 0, F.aggregate(rest, F.col("all")[0], fold)).alias("inbox"))
    if exchange in ("hash_sort", "sorted"):
        sent = combined_at_sender(messages, combine)
        sent = sent.sortWithinPartitions("dst") if exchange == "sorted" else sent
        return sent.repartition(n, "dst").sortWithinPartitions("dst").groupBy("dst").agg(f("payload").alias("inbox"))
    if exchange != "hash_agg":
        raise ValueError(f"unknown exchange {exchange}")
    return messages.groupBy("dst").agg(f("payload").alias("inbox"))


def run_vertex(
    program: VertexProgram,
    graph: VertexGraph,
    max_supersteps: int,
    exchange: str = "hash_agg",
    store: str = "replace",
    early_grouping: bool = True,
    join: str | None = None,
    truncation: Truncation | None = None,
    to_fixpoint: bool = False,
) -> tuple[DataFrame, RunReport]:
    """(id, state) when no vertex sends any more or after max_supersteps, and the report. to_fixpoint: an error if vertices are still active then.

    store: `replace` carries every vertex over with its newest state; `append_latest` keeps a log (step, id, state) and takes the latest; `delta_merge`
    keeps a base and the changes since, merged when the changes pass half of the base. join: a hint for state and messages.
    """
    g = graph.prepared()
    start = g.vertices.select("id", program.init().alias("state")).withColumns({"old": F.lit(None).cast("string"), "awake": F.lit(True), "step": F.lit(-1)})
    kind = start.schema["state"].dataType
    start = start.withColumn("old", F.lit(None).cast(kind))
    keep = truncation or Truncation()
    if g.hubs is not None:
        if store != "replace" or truncation:
            raise ValueError("states of a graph with hubs are replaced and kept in buckets")
        start = keyed_version(start, "state", "id", int(start.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    log: list[DataFrame] = []
    shared = {f"agg_{k}": f for k, f in (program.aggregates or {}).items()}
    told = dict.fromkeys(shared)
    kinds = {k: start.agg(f().alias(k)).schema[k].dataType for k, f in shared.items()}

    def senders(state: DataFrame) -> DataFrame:
        return state.where("awake")

    def along_edges(mail: DataFrame) -> DataFrame:
        """Mail with the edges it goes along. The edges are the streamed side of the join: a sort-merge join holds all rows of a key of its right side."""
        if g.hubs is None:
            return g.edges.join(mail, "src")
        hub = F.col("src").isin(g.hubs)
        n = mail.agg(F.count(F.when(hub, 1)).alias("hubs"), F.count(F.when(~hub, 1)).alias("others")).first()
        from_hubs, others = g.hub_edges.join(F.broadcast(mail.where(hub)), "src"), g.edges.join(mail.where(~hub), "src")
        if n.hubs and n.others:
            return others.unionByName(from_hubs)
        return from_hubs if n.hubs else others

    def step(j: int, state: DataFrame):
        s = F.lit(j)
        globals_ = {k: F.lit(v).cast(kinds[k]) for k, v in told.items()}
        out = senders(state).select(F.col("id").alias("src"), "state", "old", s.alias("step"), *[c.alias(k) for k, c in globals_.items()])
        mail = out.where(program.send_if()) if program.send_if else out
        sent = []
        if program.emit:
            sent.append(along_edges(mail).select("dst", program.emit().alias("payload")))
        if program.send:
            sent.append(mail.select(F.explode(program.send()).alias("m")).select(F.col("m.dst").alias("dst"), F.col("m.payload").alias("payload")))
        messages = sent[0] if len(sent) == 1 else sent[0].unionByName(sent[1])
        inbox = deliver(messages, program.combine, exchange, early_grouping)
        if program.stay:  # activations: no payload, but the vertex runs
            inbox = inbox.unionByName(out.where(program.stay()).select(F.col("src").alias("dst"), F.lit(None).cast(inbox.schema["inbox"].dataType).alias("inbox")))
            inbox = inbox.groupBy("dst").agg(F.max("inbox").alias("inbox"))
        inbox = inbox.withColumn("mail", F.lit(True))
        new_ids = program.on_unknown == "create"
        merged = state.join(inbox.hint(join) if join else inbox, F.col("id") == F.col("dst"), "full" if new_ids else "left")
        merged = merged.withColumn("id", F.coalesce("id", "dst")) if new_ids else merged
        ran = F.coalesce("mail", F.lit(False))
        seen = merged.withColumns({"step": s} | globals_).withColumn("new", F.when(ran, program.update()))
        nxt = seen.select("id", F.coalesce("new", "state").alias("state"), F.col("state").alias("old"), ran.alias("awake"), "step")
        if store == "append_latest":
            log.append(keep.keep(nxt.where("awake").select("id", "state", "old", "awake", "step"), j))
            everything = start.withColumn("awake", F.lit(False))
            for x in log:
                everything = everything.unionByName(x)
            latest = everything.groupBy("id").agg(F.max_by(F.struct("state", "old", "step"), "step").alias("m"))
            nxt = latest.select("id", "m.state", F.when(F.col("m.step") == j, F.col("m.old")).otherwise(F.col("m.state")).alias("old"), (F.col("m.step") == j).alias("awake"), s.alias("step"))
        elif store == "delta_merge":
            base, delta = state.select("id", "state"), nxt.where("awake")
            rest = base.join(delta.select("id"), "id", "left_anti").select("id", "state", F.col("state").alias("old"), F.lit(False).alias("awake"), s.alias("step"))
            nxt = delta.unionByName(rest)
        nxt = keep.keep(nxt, j + 1) if g.hubs is None else keyed_version(nxt, "state", "id")
        changed = F.sum(F.when(~F.col("state").eqNullSafe(F.col("old")), 1).otherwise(0))
        row = nxt.agg(F.sum(F.col("awake").cast("long")).alias("active"), changed.alias("changed"), *[f().alias(k) for k, f in shared.items()]).first()
        told.update({k: row[k] for k in told})
        if g.hubs is not None:
            forget(state)
        return nxt, {"active": int(row.active or 0), "delta": float(row.changed or 0)}

    def stop(j: int, m: dict) -> bool:
        return j >= max_supersteps or m["active"] == 0

    if max_supersteps <= 0:
        return start.select("id", "state"), RunReport()
    state, report = FixpointDriver(lambda: start, step, stop, keep).run()
    g.edges.unpersist()
    if to_fixpoint and report.active and report.active[-1]:
        raise RuntimeError(f"still active after {max_supersteps} supersteps: the result would not be a fixpoint")
    return state.select("id", "state"), report
