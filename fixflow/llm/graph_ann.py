"""Approximate nearest neighbours over robust-pruned directed graphs, one for each shard.

Vectors are dealt into shards of about ``shard_rows`` by a hash of their id. A shard's graph starts random; in two passes
(relaxation 1, then ``alpha``) batches of nodes search greedily from the medoid, the nodes they evaluate become candidates, and robust pruning keeps the
nearest candidate and drops those that are ``alpha`` times nearer to it than to the node, again and again, which leaves diverse edges. Reverse edges are
added and pruned alike. Every row is indexed; all arithmetic on a batch is numpy on whole blocks.

Queries travel to every shard in parts of about ``QUERY_PART``; a shard's graph is sent once for each part, so what is shuffled is at most about twice the queries
times the shards, whatever their number. Each part meets one graph in one task, which searches block by block. A beam search collects ``beam`` candidates there, their cosines are computed in double precision on the original
vectors, and the best of all shards are kept. A shard that holds no more rows than the beam is searched exhaustively, so few candidates are never missed.

Vectors that are null, zero, or have null or non-finite components take no part, on either side. Rows with a null id take no part. Rows that repeat an
id with its vector count once, as candidates and as queries. Rows with one id and several vectors are candidates and queries of their own, but never candidates of a query with that id. Ties go to the smaller id. Vectors of another length than the query's are no candidates. An empty
table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import durable, table

DEGREE, BEAM, ALPHA, SHARD_ROWS, QUERY_BLOCK, QUERY_PART = 32, 96, 1.2, 6000, 512, 16384
NO_ID = np.int64(-(2**63))


def prune(x: np.ndarray, node: np.ndarray, cand: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """Robust pruning of candidates [nodes, c] (-1: none) of unit vectors x; returns edges [nodes, degree]."""
    c = cand.shape[1]
    dup = np.sort(cand, 1)
    order = np.argsort(cand, 1, kind="stable")
    same = np.zeros_like(cand, bool)
    np.put_along_axis(same, order, np.concatenate([np.zeros((len(cand), 1), bool), dup[:, 1:] == dup[:, :-1]], 1), 1)
    alive = (cand >= 0) & (cand != node[:, None]) & ~same
    v = x[np.maximum(cand, 0)]
    to_node = np.where(alive, 1 - np.einsum("bcd,bd->bc", v, x[node]), np.inf).astype(np.float32)
    between = 1 - np.matmul(v, v.transpose(0, 2, 1))
    out = np.full((len(node), degree), -1, np.int32)
    rows = np.arange(len(node))
    for k in range(min(degree, c)):
        best = to_node.argmin(1)
        ok = np.isfinite(to_node[rows, best])
        if not ok.any():
            break
        out[ok, k] = cand[rows[ok], best[ok]]
        near = between[rows, best]
        to_node = np.where(ok[:, None] & (alpha * near <= to_node), np.inf, to_node)
        to_node[rows, best] = np.inf
    return out


def search(x: np.ndarray, graph: np.ndarray, start: int, q: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
    """Beam search of unit queries q in lockstep: the nodes of the final beams and all nodes that were expanded (-1: none)."""
    m, n = len(q), len(x)
    ids = np.full((m, beam), -1, np.int64)
    dist = np.full((m, beam), np.inf, np.float32)
    open_ = np.zeros((m, beam), bool)
    ids[:, 0], dist[:, 0], open_[:, 0] = start, 1 - q @ x[start], True
    seen = np.zeros((m, n), bool)
    seen[:, start] = True
    trail = []
    rows = np.arange(m)
    while True:
        pick = np.where(open_, dist, np.inf).argmin(1)
        go = open_[rows, pick]
        if not go.any():
            break
        open_[rows, pick] = False
        r = rows[go]
        at = ids[r, pick[r]]
        step = np.full(m, -1, np.int64)
        step[r] = at
        trail.append(step)
        nb = graph[at].astype(np.int64)
        fresh = (nb >= 0) & ~seen[r[:, None], np.maximum(nb, 0)]
        seen[np.broadcast_to(r[:, None], nb.shape)[fresh], nb[fresh]] = True
        d = np.where(fresh, 1 - np.einsum("bcd,bd->bc", x[np.maximum(nb, 0)], q[r]), np.inf).astype(np.float32)
        all_d = np.concatenate([dist[r], d], 1)
        all_i = np.concatenate([ids[r], np.where(fresh, nb, -1)], 1)
        all_o = np.concatenate([open_[r], fresh], 1)
        top = np.argpartition(all_d, beam - 1, 1)[:, :beam]
        dist[r], ids[r] = np.take_along_axis(all_d, top, 1), np.take_along_axis(all_i, top, 1)
        open_[r] = np.take_along_axis(all_o, top, 1)
    return ids, np.stack(trail, 1) if trail else np.full((m, 1), -1, np.int64)


def build(x: np.ndarray, degree: int = DEGREE, beam: int = 64, alpha: float = ALPHA, batch: int = 256) -> tuple[np.ndarray, int]:
    """Graph [rows, degree] over unit vectors and its entry."""
    n = len(x)
    rng = np.random.default_rng(n)
    graph = rng.integers(0, max(n, 1), (n, degree)).astype(np.int32)
    graph[graph == np.arange(n)[:, None]] = -1
    start = int((x @ x.mean(0)).argmax())
    for a in (1.0, alpha):
        for part in np.array_split(rng.permutation(n), -(-n // batch)):
            _, trail = search(x, graph, start, x[part], beam)
            graph[part] = prune(x, part, np.concatenate([trail, graph[part]], 1), degree, a)
            src, dst = np.repeat(part, degree), graph[part].ravel()
            src, dst = src[dst >= 0], dst[dst >= 0]
            order = np.argsort(dst, kind="stable")
            src, dst = src[order], dst[order]
            to, first, many = np.unique(dst, return_index=True, return_counts=True)
            extra = np.full((len(to), int(many.max()) if len(to) else 0), -1, np.int64)
            extra[np.repeat(np.arange(len(to)), many), np.arange(len(dst)) - np.repeat(first, many)] = src
            both = np.concatenate([graph[to], extra], 1)
            for i in range(0, len(to), 1024):  # bounded memory where a node has many new reverse edges
                graph[to[i : i + 1024]] = prune(x, to[i : i + 1024], both[i : i + 1024], degree, a)
    return graph, start


def usable(vectors: DataFrame, vec_id: str, embedding: str) -> DataFrame:
    v = F.transform(F.col(embedding), lambda e: e.cast("double"))
    fine = F.col("v").isNotNull() & F.forall("v", lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < float("inf"))) & F.exists("v", lambda e: e != 0)
    return vectors.select(F.col(vec_id).cast("long").alias("id"), v.alias("v")).where(F.col("id").isNotNull() & fine)


def nearest(vectors: DataFrame, every: int = 50, k: int = 5, beam: int = BEAM, degree: int = DEGREE, shard_rows: int = SHARD_ROWS, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: for rows whose id is divisible by `every`, the k rows of largest cosine found."""
    rows = usable(vectors, vec_id, embedding)
    shards = max(1, -(-rows.count() // shard_rows))

    def index(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id", kind="stable")
        x = np.array(pdf["v"].tolist(), np.float64) + 0.0
        # equal vectors are one node; beyond its k + 1 smallest ids none can be among a query's k nearest
        _, first, of = np.unique(np.ascontiguousarray(x).view(f"V{8 * x.shape[1]}").ravel(), return_index=True, return_inverse=True)
        node, own_id = np.unique(np.stack([of, pdf["id"].to_numpy()], 1), axis=0).T
        nth = np.arange(len(node)) - np.searchsorted(node, node)
        ids = np.full((len(first), k + 1), NO_ID)
        ids[node[nth <= k], nth[nth <= k]] = own_id[nth <= k]
        x = x[first]
        unit = scaled(x).astype(np.float32)
        graph, start = build(unit, degree)
        return pd.DataFrame({"shard": pdf["shard"].iloc[:1], "dim": [x.shape[1]], "start": [start], "ids": [ids.tobytes()], "x": [x.tobytes()], "graph": [graph.tobytes()]})

    dealt = rows.withColumn("shard", F.pmod(F.xxhash64("id", "v"), F.lit(shards)).cast("int")).withColumn("dim", F.size("v"))
    built = durable(dealt.groupBy("shard", "dim").applyInPandas(index, "shard int, dim int, start int, ids binary, x binary, graph binary"), "graphs")

    def find(graphs: pd.DataFrame, blocks: pd.DataFrame) -> pd.DataFrame:
        out: list = []
        if len(graphs) and len(blocks):
            s = graphs.iloc[0]
            ids, dim = np.frombuffer(s["ids"], np.int64).reshape(-1, k + 1), int(s["dim"])
            x = np.frombuffer(s["x"], np.float64).reshape(-1, dim)
            graph, unit = np.frombuffer(s["graph"], np.int32).reshape(len(ids), -1), scaled(x)
            single = unit.astype(np.float32)
            for b_ids, b_vectors in zip(blocks["q_ids"], blocks["q"]):
                q_id, q = np.frombuffer(b_ids, np.int64), np.frombuffer(b_vectors, np.float64).reshape(-1, dim)
                if len(ids) <= beam:
                    found = np.broadcast_to(np.arange(len(ids)), (len(q), len(ids)))
                else:
                    found, _ = search(single, graph, int(s["start"]), scaled(q).astype(np.float32), beam)
                for i in range(len(q)):
                    f = found[i][found[i] >= 0]
                    score, own = np.repeat(cosine(x[f], q[i]), k + 1), ids[f].ravel()
                    score = np.where((own == NO_ID) | (own == q_id[i]), -np.inf, score)
                    best = np.lexsort((own, -score))[:k]
                    key = q[i].tobytes()
                    out += [(q_id[i], key, own[b], score[b]) for b in best if score[b] > -np.inf]
        return pd.DataFrame(out, columns=["query_id", "q", "vec_id", "score"])

    def block(batches):
        for pdf in batches:
            for dim, part in pdf.groupby("dim"):
                for i in range(0, len(part), QUERY_BLOCK):
                    p = part.iloc[i : i + QUERY_BLOCK]
                    yield pd.DataFrame({"dim": [dim], "q_ids": [p["id"].to_numpy().tobytes()], "q": [np.array(p["v"].tolist(), np.float64).tobytes()]})

    asked = dealt.where(F.col("id") % every == 0).select("id", "v", "dim").dropDuplicates(["id", "v"])
    parts = max(1, -(-asked.count() // QUERY_PART))
    blocks = asked.mapInPandas(block, "dim int, q_ids binary, q binary").withColumn("part", F.pmod(F.xxhash64("q_ids"), F.lit(parts)).cast("int"))
    blocks = blocks.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))
    graphs = built.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    best = graphs.groupBy("shard", "dim", "part").cogroup(blocks.groupBy("shard", "dim", "part")).applyInPandas(find, "query_id long, q binary, vec_id long, score double")
    ranked = best.withColumn("rank", F.row_number().over(Window.partitionBy("query_id", "q").orderBy(F.desc("score"), "vec_id")))
    return ranked.where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int"), "vec_id", "score")


def scaled(x: np.ndarray) -> np.ndarray:
    big = np.abs(x).max(1, keepdims=True) if len(x) else np.ones((0, 1))
    x = x / big  # so squares neither overflow nor vanish
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def cosine(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    return scaled(x) @ scaled(q[None])[0]


def op3(spark, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"))
