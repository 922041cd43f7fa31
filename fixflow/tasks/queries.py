"""Queries of the graph and learning tasks, their variants and baselines, with oracles as unrolled or recursive SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..baselines.runs import bgd_as_vertices, inmem_bgd, keyed_statistic, rank_on_mru, statistic_on_vertices, two_job_rank
from ..catalog import query
from ..functions.losses import SLOPE_SQL, VALUE_SQL
from ..functions.measures import cost_optimal_points
from ..operators.reduce import reduced
from ..plans.cost import reduce_cost_columns
from ..runtime import version
from ..sources.tables import GRAPH_SQL, TRAIN_SQL, duplicate_graph, duplicate_records, graph, table, training
from . import graphs as G
from . import learning as L

DAMPING, ROUNDS = 0.85, 10


def rank_sql(edges: str, rounds: int = ROUNDS, top: int | None = None, dangling: str = "drop", exact: bool = False) -> str:
    weighted = "weight" in edges
    share = "e.weight::double / g.deg" if weighted else "1.0 / g.deg"
    parts = [f"with e as materialized ({edges})", "v as materialized (select src as id from e union select dst from e)", f"g as materialized (select src, {'sum(weight)' if weighted else 'count(*)'} as deg from e group by 1)", "n as materialized (select count(*) as n from v)"]
    parts.append("r0 as materialized (select id, " + ("1000000000000 // n" if exact else "1.0/n") + " as r from v, n)")
    for k in range(rounds):
        if exact:
            parts.append(f"r{k + 1} as materialized (select v.id, 150000000000 // n + (85 * coalesce(c.s, 0)) // 100 as r from v cross join n left join (select e.dst, cast(sum(r.r // g.deg) as bigint) as s from r{k} r join e on e.src = r.id join g on g.src = r.id group by 1) c on c.dst = v.id)")
            continue
        lost = f" + coalesce((select sum(r) from r{k} where id not in (select src from g)), 0)/n" if dangling == "redistribute" else ""
        parts.append(f"r{k + 1} as materialized (select v.id, 0.15/n + 0.85*(coalesce(c.s, 0){lost}) as r from v cross join n left join (select e.dst, sum(r.r * {share}) as s from r{k} r join e on e.src = r.id join g on g.src = r.id group by 1) c on c.dst = v.id)")
    out = f"select id, {'r' if exact else 'round(r, 9)'} as rank from r{rounds}"
    if top:
        out = f"select id, rank from ({out}) order by rank desc, id limit {top}"
    return ", ".join(parts) + " " + out


def out9(ranks: DataFrame) -> DataFrame:
    return ranks.select("id", F.round("rank", 9).alias("rank"))


PS = rank_sql(GRAPH_SQL["g_part_supp"])


def ranking(name: str, graph_name: str, sql: str, **options):
    @query(name, sql)
    def run(spark, d):
        return out9(G.pagerank(graph(spark, d, graph_name), DAMPING, ROUNDS, **options)[0])


ranking("pagerank_part_supp", "g_part_supp", PS)
ranking("pagerank_cust_part", "g_cust_part", rank_sql(GRAPH_SQL["g_cust_part"]))
ranking("pagerank_pages", "g_pages", rank_sql(GRAPH_SQL["g_pages"], dangling="redistribute"), dangling="redistribute")
ranking("pagerank_weighted_user_next", "g_user_next", rank_sql(GRAPH_SQL["g_user_next"]))
for kind in ("hash_agg", "hash_sort", "sorted"):
    ranking(f"pagerank_exchange_{kind}", "g_part_supp", PS, exchange=kind)
for kind in ("append_latest", "replace", "delta_merge"):
    ranking(f"pagerank_store_{kind}", "g_part_supp", PS, store=kind)
ranking("pagerank_no_early_grouping", "g_part_supp", PS, early_grouping=False)


@query("pagerank_dense_plan", PS)
def pagerank_dense_plan(spark, d):
    return out9(G.pagerank_dense(graph(spark, d, "g_part_supp"), DAMPING, ROUNDS))


@query("topk_rank", rank_sql(GRAPH_SQL["g_part_supp"], top=20))
def topk_rank(spark, d):
    return out9(G.pagerank_dense(graph(spark, d, "g_part_supp"), DAMPING, ROUNDS)).orderBy(F.desc("rank"), "id").limit(20)


@query("pagerank_delta_part_supp", PS)
def pagerank_delta_part_supp(spark, d):
    return out9(G.pagerank_delta(graph(spark, d, "g_part_supp"), DAMPING, ROUNDS, 0.0)[0])


@query("pagerank_exact_part_supp", rank_sql(GRAPH_SQL["g_part_supp"], exact=True))
def pagerank_exact_part_supp(spark, d):
    return G.pagerank_exact(graph(spark, d, "g_part_supp"), ROUNDS)


@query("pagerank_duplicated_x2", rank_sql("with g0 as (" + GRAPH_SQL["g_part_supp"] + "), m as (select max(greatest(src, dst)) + 1 as m from g0) select src + i*m as src, dst + i*m as dst from g0, m, (values (0), (1)) t(i)"))
def pagerank_duplicated_x2(spark, d):
    return out9(G.pagerank_dense(duplicate_graph(graph(spark, d, "g_part_supp"), 2), DAMPING, ROUNDS))


@query("pagerank_two_job", PS)
def pagerank_two_job(spark, d):
    return out9(two_job_rank(graph(spark, d, "g_part_supp"), DAMPING, ROUNDS))


@query("join_two_job", "with e as (" + GRAPH_SQL["g_part_supp"] + "), g as (select src, count(*) as deg from e group by 1) select e.dst as id, round(sum(1.0/g.deg), 6) as c from e join g on e.src = g.src group by 1")
def join_two_job(spark, d):
    e = graph(spark, d, "g_part_supp")
    rank = e.groupBy(F.col("src").alias("id")).agg((1.0 / F.count("*")).alias("share"))
    return e.hint("merge").join(rank, F.col("src") == F.col("id")).groupBy(F.col("dst").alias("id")).agg(F.round(F.sum("share"), 6).alias("c"))


@query("rank_on_mru_user_next", rank_sql(GRAPH_SQL["g_user_next"].replace("count(*) as weight", "1 as w0")))
def rank_on_mru_user_next(spark, d):
    ranks = rank_on_mru(graph(spark, d, "g_user_next").select("src", "dst"), DAMPING, ROUNDS)
    return spark.createDataFrame([(k, round(v, 9)) for k, v in ranks.items()], "id string, rank double")


UND = "select src, dst from ({e}) union select dst, src from ({e})"


def component_sql(edges: str) -> str:
    return f"with recursive u as materialized ({UND.format(e=edges)}), c(id, component) using key (id) as (select id, id from (select distinct src as id from u) union (select u.dst, min(c.component) from c join u on c.id = u.src join recurring.c as old on old.id = u.dst where c.component < old.component group by u.dst)) select id, component from c"


@query("components_part_supp", component_sql(GRAPH_SQL["g_part_supp"]))
def components_part_supp(spark, d):
    return G.connected_components(graph(spark, d, "g_part_supp"))[0]


@query("components_turns", "with e as (" + GRAPH_SQL["g_turns"] + "), v as (select src as id from e union select dst from e) select id, min(id) over (partition by id // 1000) as component from v")
def components_turns(spark, d):
    return G.connected_components(graph(spark, d, "g_turns"))[0]


def _level_sql(edges: str, source: str) -> str:
    return f"with recursive e as materialized ({edges}), v as (select src as id from e union select dst from e), b(id, k) as (select {source}, cast(0 as bigint) union select e.dst, b.k + 1 from b join e on e.src = b.id where b.k < 40) select v.id, x.distance from v left join (select id, min(k) as distance from b group by 1) x on x.id = v.id"


@query("sssp_part_supp", "with recursive e as materialized (" + GRAPH_SQL["g_part_supp"] + "), v as materialized (select src as id from e union select dst from e), b(id, k) using key (id) as (select min(id), cast(0 as bigint) from v union (select e.dst, min(b.k) + 1 from b join e on e.src = b.id left join recurring.b as old on old.id = e.dst where old.id is null group by e.dst)) select v.id, b.k as distance from v left join b on b.id = v.id")
def sssp_part_supp(spark, d):
    e = graph(spark, d, "g_part_supp")
    return G.sssp(e, e.agg(F.min("src").alias("id")))[0]


@query("bfs_levels_turns", "with e as (" + GRAPH_SQL["g_turns"] + "), v as (select src as id from e union select dst from e) select id, cast(row_number() over (partition by id // 1000 order by id) - 1 as bigint) as distance from v")
def bfs_levels_turns(spark, d):
    e = graph(spark, d, "g_turns")
    heads = e.select(F.col("src").alias("id")).join(e.select(F.col("dst").alias("id")), "id", "left_anti")
    return G.sssp(e, heads)[0]


@query("active_counts_by_superstep", "with e as (" + GRAPH_SQL["g_turns"] + "), v as (select src as id from e union select dst from e), l as (select row_number() over (partition by id // 1000 order by id) - 1 as k from v) select cast(k as bigint) as superstep, count(*) as active from l where k > 0 group by 1")
def active_counts_by_superstep(spark, d):
    e = graph(spark, d, "g_turns")
    heads = e.select(F.col("src").alias("id")).join(e.select(F.col("dst").alias("id")), "id", "left_anti")
    _, report = G.sssp(e, heads)
    return spark.createDataFrame([(k + 1, a) for k, a in enumerate(report.active) if a], "superstep long, active long")


LP = "with e as materialized ({e}), l0 as (select src as id, src as label from e union select dst, dst from e)".format(e=GRAPH_SQL["g_user_next"])
for _k in range(3):
    LP += f", l{_k + 1} as (select l.id, coalesce(b.label, l.label) as label from l{_k} l left join (select dst, label from (select e.dst, s.label, row_number() over (partition by e.dst order by sum(e.weight) desc, s.label) as k from e join l{_k} s on s.id = e.src group by 1, 2) where k = 1) b on b.dst = l.id)"


@query("label_propagation_user_next", LP + " select id, label from l3")
def label_propagation_user_next(spark, d):
    return G.label_propagation(graph(spark, d, "g_user_next"), 3)


@query("degree_stats_part_supp", "with e as (" + GRAPH_SQL["g_part_supp"] + ") select id, sum(o)::bigint as out_degree, sum(i)::bigint as in_degree from (select src as id, 1 as o, 0 as i from e union all select dst, 0, 1 from e) group by 1")
def degree_stats_part_supp(spark, d):
    return G.degree_stats(graph(spark, d, "g_part_supp"))


def _core_sql(k: int, rounds: int) -> str:
    """Peeling, unrolled: rounds beyond the fixpoint change nothing."""
    parts = [f"c0 as materialized ({GRAPH_SQL['g_part_supp']})"]
    for j in range(rounds):
        parts.append(f"d{j} as materialized (select src as id from c{j} group by 1 having count(*) >= {k})")
        parts.append(f"c{j + 1} as materialized (select src, dst from c{j} where src in (select id from d{j}) and dst in (select id from d{j}))")
    return "with " + ", ".join(parts) + f" select distinct src as id from c{rounds}"


@query("k_core_part_supp", _core_sql(20, 40))
def k_core_part_supp(spark, d):
    return G.k_core(graph(spark, d, "g_part_supp"), 20)


def _hits_sql(rounds: int) -> str:
    parts = [f"e as ({GRAPH_SQL['g_pages']})", "v as (select src as id from e union select dst from e)", "h0 as (select id, 1.0::double as x from v)"]
    for j in range(1, rounds + 1):
        for new, old, near, far in ((f"a{j}", f"h{j - 1}", "dst", "src"), (f"h{j}", f"a{j}", "src", "dst")):
            parts.append(f"{new}r as (select v.id, coalesce(sum(o.x), 0) as x from v left join e on e.{near} = v.id left join {old} o on o.id = e.{far} group by v.id)")
            parts.append(f"{new} as materialized (select id, x / (select sqrt(sum(x * x)) from {new}r) as x from {new}r)")
    return "with " + ", ".join(parts) + f" select a.id, round(h.x, 9) as hub, round(a.x, 9) as authority from a{rounds} a join h{rounds} h using (id)"


@query("hits_pages", _hits_sql(5))
def hits_pages(spark, d):
    return G.hits(graph(spark, d, "g_pages"), 5).select("id", F.round("hub", 9).alias("hub"), F.round("authority", 9).alias("authority"))


TRIPLES = "select distinct o_custkey * 3 as c, l_partkey * 3 + 1 as p, l_suppkey * 3 + 2 as s from lineitem join orders on l_orderkey = o_orderkey"


@query(
    "triangles_cust_part_supp",
    f"with t as ({TRIPLES}), f as (select x.c, x.p, y.s from (select distinct c, p from t) x join (select distinct p, s from t) y using (p) join (select distinct c, s from t) z on z.c = x.c and z.s = y.s) "
    "select id, count(*) as triangles from (select c as id from f union all select p from f union all select s from f) group by id",
)
def triangles_cust_part_supp(spark, d):
    """Customer, part and supplier of a line are joined by edges; triangles arise across lines too."""
    lines, orders = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("lineitem", "orders"))
    t = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select((F.col("o_custkey") * 3).alias("c"), (F.col("l_partkey") * 3 + 1).alias("p"), (F.col("l_suppkey") * 3 + 2).alias("s"))
    return G.triangle_count(t.select(F.explode(F.array(*[F.struct(F.col(a).alias("src"), F.col(b).alias("dst")) for a, b in ("cp", "ps", "sc")])).alias("e")).select("e.*"))


@query("triangles_cust_part_none", "select cast(0 as bigint) as triangles")
def triangles_cust_part_none(spark, d):
    """A bipartite graph has none."""
    return G.triangle_count(graph(spark, d, "g_cust_part")).agg(F.coalesce(F.sum("triangles"), F.lit(0)).cast("long").alias("triangles"))


# --- learning ---

DENSE = ["x0", "x1", "x2", "x3"]


def bgd_sql(data: str, features: list[str], loss: str, eta: float, l2: float, rounds: int, last: str, copies: int = 1) -> str:
    out = f"with d as materialized ({data})"
    zero = ", ".join(f"0.0::double as w{k}" for k in range(len(features)))
    out += f", m0 as (select {zero})"
    for j in range(rounds):
        p = "(" + " + ".join(f"w{k}*{f}" for k, f in enumerate(features)) + ")"
        slope, value = SLOPE_SQL[loss].format(p=p, y="y"), VALUE_SQL[loss].format(p=p, y="y")
        news = ", ".join(f"any_value(w{k}) - {eta}*(sum({slope}*{f})/count(*)" + (f" + {l2}*any_value(w{k})" if l2 and k else "") + f") as w{k}" for k, f in enumerate(features))
        out += f", s{j} as materialized (select {news}, sum({value})/count(*) as loss from d, m{j}), m{j + 1} as (select {', '.join(f'w{k}' for k in range(len(features)))} from s{j})"
    return out + " " + last


W_ROW = "select " + ", ".join(f"round(w{k}, 6) as w{k}" for k in range(4)) + " from m5"


def w_row(spark, w: list[float]) -> DataFrame:
    return spark.createDataFrame([tuple(float(round(v, 6)) for v in w)], ", ".join(f"w{k} double" for k in range(len(w))))


@query("bgd_squared_lineitem", bgd_sql(TRAIN_SQL["x_lineitem"], DENSE, "squared", 0.5, 0.0, 5, W_ROW))
def bgd_squared_lineitem(spark, d):
    return w_row(spark, L.bgd(training(spark, d, "x_lineitem"), DENSE)[0])


@query("bgd_auto_topology_lineitem", bgd_sql(TRAIN_SQL["x_lineitem"], DENSE, "squared", 0.5, 0.0, 5, W_ROW))
def bgd_auto_topology_lineitem(spark, d):
    """The reduce topology is chosen by the cost rules from the session's executors."""
    return w_row(spark, L.bgd(training(spark, d, "x_lineitem"), DENSE, topology="auto")[0])


@query("bgd_l2_lineitem", bgd_sql(TRAIN_SQL["x_lineitem"], DENSE, "squared", 0.5, 0.1, 5, W_ROW))
def bgd_l2_lineitem(spark, d):
    return w_row(spark, L.bgd(training(spark, d, "x_lineitem"), DENSE, l2=0.1)[0])


@query("bgd_duplicated_x2", bgd_sql(TRAIN_SQL["x_lineitem"], DENSE, "squared", 0.5, 0.0, 5, W_ROW))
def bgd_duplicated_x2(spark, d):
    return w_row(spark, L.bgd(duplicate_records(training(spark, d, "x_lineitem"), 2), DENSE)[0])


@query("bgd_inmem_lineitem", bgd_sql(TRAIN_SQL["x_lineitem"], DENSE, "squared", 0.5, 0.0, 5, W_ROW))
def bgd_inmem_lineitem(spark, d):
    return w_row(spark, inmem_bgd(training(spark, d, "x_lineitem"), DENSE)[0])


@query("bgd_as_vertices_lineitem", bgd_sql(TRAIN_SQL["x_lineitem"], DENSE, "squared", 0.5, 0.0, 5, W_ROW))
def bgd_as_vertices_lineitem(spark, d):
    x = training(spark, d, "x_lineitem")
    return w_row(spark, bgd_as_vertices(x.withColumn("id", F.monotonically_increasing_id()), DENSE))


TRACE = " union all ".join(f"select cast({j} as bigint) as iteration, round(loss, 6) as loss from s{j}" for j in range(5))


@query("bgd_loss_trace_lineitem", bgd_sql(TRAIN_SQL["x_lineitem"], DENSE, "squared", 0.5, 0.0, 5, TRACE))
def bgd_loss_trace_lineitem(spark, d):
    _, report, _ = L.bgd(training(spark, d, "x_lineitem"), DENSE)
    return spark.createDataFrame([(j, float(round(x, 6))) for j, x in enumerate(report.loss)], "iteration long, loss double")


BY_ROUND = " union all ".join(f"select cast({j} as bigint) as iteration, " + ", ".join(f"round(w{k}, 6) as w{k}" for k in range(4)) + f" from m{j}" for j in range(6))


@query("bgd_weights_by_iteration", bgd_sql(TRAIN_SQL["x_lineitem"], DENSE, "squared", 0.5, 0.0, 5, BY_ROUND))
def bgd_weights_by_iteration(spark, d):
    _, _, models = L.bgd(training(spark, d, "x_lineitem"), DENSE)
    return spark.createDataFrame([(j, *[float(round(v, 6)) for v in w]) for j, w in enumerate(models)], "iteration long, w0 double, w1 double, w2 double, w3 double")


def sparse_sql(entries: str, records: str, loss: str, eta: float, rounds: int) -> str:
    """entries: (id, feature, x); records: (id, y)."""
    out = f"with x as materialized ({entries}), r as materialized ({records}), n as (select count(*) as n from r), m0 as (select distinct feature, 0.0::double as w from x)"
    for j in range(rounds):
        out += f", p{j} as materialized (select r.id, {SLOPE_SQL[loss].format(p='coalesce(t.p, 0)', y='r.y')} as s from r left join (select x.id, sum(x.x*m.w) as p from x join m{j} m on m.feature = x.feature group by 1) t on t.id = r.id)"
        out += f", m{j + 1} as materialized (select m.feature, m.w - {eta}*coalesce(g.g, 0)/n as w from m{j} m cross join n left join (select x.feature, sum(x.x*p.s) as g from x join p{j} p on p.id = x.id group by 1) g on g.feature = m.feature)"
    return out + f" select feature, round(w, 6) + 0.0 as weight from m{rounds}"  # no negative zeros


EVENTS_SQL = sparse_sql("select event_id as id, f as feature, 1.0 as x from (" + TRAIN_SQL["x_events"] + ")", "select event_id as id, case when event_type='purchase' then 1 else 0 end as y from events", "logistic", 0.5, 5)


@query("bgd_logistic_events", EVENTS_SQL)
def bgd_logistic_events(spark, d):
    """Sparse records with a dense model of 95 weights: the model is a literal array, gradients are summed in long form by feature."""
    x = training(spark, d, "x_events")
    w = [0.0] * 95
    n = x.count()
    for _ in range(5):
        p = F.aggregate(F.transform("f", lambda i: F.element_at(F.array(*[F.lit(float(v)) for v in w]), (i + 1).cast("int"))), F.lit(0.0), lambda s, v: s + v)
        slope = F.lit(1.0) / (F.lit(1.0) + F.exp(-p)) - F.col("y")
        g = x.select(F.explode("f").alias("feature"), slope.alias("s")).groupBy("feature").agg(F.sum("s").alias("g")).collect()  # 95 rows at most
        for r in g:
            w[r.feature] -= 0.5 * r.g / n
    used = x.select(F.explode("f").alias("feature")).distinct()
    model = spark.createDataFrame([(k, float(round(v, 6))) for k, v in enumerate(w)], "feature long, weight double")
    return model.join(used, "feature", "left_semi")


@query("bgd_feature_table_events", EVENTS_SQL)
def bgd_feature_table_events(spark, d):
    x = training(spark, d, "x_events").withColumnRenamed("event_id", "id")
    w = L.bgd_feature_table(x.select("id", "y"), x.select("id", F.explode("f").alias("feature"), F.lit(1.0).alias("x")))
    return w.select("feature", F.round("weight", 6).alias("weight"))


@query("bgd_feature_table_shuffled_events", EVENTS_SQL)
def bgd_feature_table_shuffled_events(spark, d):
    """The layout for models too large to broadcast."""
    x = training(spark, d, "x_events").withColumnRenamed("event_id", "id")
    w = L.bgd_feature_table(x.select("id", "y"), x.select("id", F.explode("f").alias("feature"), F.lit(1.0).alias("x")), layout="feature_table")
    return w.select("feature", F.round("weight", 6).alias("weight"))


DOCS_SQL = sparse_sql(
    "select doc_id as id, tok as feature, n::double as x from (" + TRAIN_SQL["x_docs_tokens"] + ")", "select distinct doc_id as id, quality as y from (" + TRAIN_SQL["x_docs_tokens"] + ")", "logistic", 0.001, 3
)


@query("bgd_logistic_docs", DOCS_SQL)
def bgd_logistic_docs(spark, d):
    """Token counts of documents: high-dimensional and sparse."""
    x = training(spark, d, "x_docs_tokens").withColumnRenamed("doc_id", "id")
    w = L.bgd_feature_table(x.select("id", F.col("quality").alias("y")).distinct(), x.select("id", F.col("tok").alias("feature"), F.col("n").cast("double").alias("x")), eta=0.001, iterations=3)
    return w.select("feature", (F.round("weight", 6) + 0.0).alias("weight"))


_EMB = "select id, y, i as feature, x[i]::double as x from (select vec_id as id, y, x, unnest(range(1, 65)) as i from (" + TRAIN_SQL["x_embed"] + "))"


@query("bgd_hinge_embeddings", sparse_sql("select id, feature, x from (" + _EMB + ")", "select vec_id as id, y from (" + TRAIN_SQL["x_embed"] + ")", "hinge", 0.5, 5))
def bgd_hinge_embeddings(spark, d):
    w, _, _ = L.bgd_dense_arrays(training(spark, d, "x_embed"), 64)
    return spark.createDataFrame([(k + 1, float(round(v, 6))) for k, v in enumerate(w)], "feature long, weight double")


@query("bgd_perceptron_embeddings", sparse_sql("select id, feature, x from (" + _EMB + ")", "select vec_id as id, y from (" + TRAIN_SQL["x_embed"] + ")", "perceptron", 0.5, 5))
def bgd_perceptron_embeddings(spark, d):
    w, _, _ = L.bgd_dense_arrays(training(spark, d, "x_embed"), 64, "perceptron")
    return spark.createDataFrame([(k + 1, float(round(v, 6))) for k, v in enumerate(w)], "feature long, weight double")


@query(
    "gaussian_bayes_embeddings",
    f"with e as materialized ({_EMB}), s as materialized (select y, feature, count(*) as n, avg(x) as m, var_pop(x) + 1e-9 as v from e group by 1, 2), "
    "p as (select e.id, e.y, s.y as c, ln(any_value(s.n)) - sum(ln(s.v) + (e.x-s.m)*(e.x-s.m)/s.v)/2 as score from e join s using (feature) group by 1, 2, 3), "
    "b as (select y, c from (select y, c, row_number() over (partition by id order by score desc, c) as k from p) where k = 1) "
    "select s.y::double as y, max(n)::bigint as n, round(max(m) filter (feature = 1), 6) as m1, round(max(v) filter (feature = 64), 6) as v64, (select count(*) from b where b.y = s.y and b.c = s.y) as correct from s group by s.y",
)
def gaussian_bayes_embeddings(spark, d):
    x = training(spark, d, "x_embed")
    model = L.gaussian_bayes(x, 64)
    right = L.gaussian_bayes_predict(x, model).groupBy("y").agg(F.count(F.when(F.col("prediction") == F.col("y"), 1)).alias("correct"))
    rows = spark.createDataFrame([(float(c), n, float(round(m[0], 6)), float(round(s[-1], 6))) for c, n, m, s in model], "y double, n long, m1 double, v64 double")
    return right.join(F.broadcast(rows), "y").select("y", "n", "m1", "v64", "correct")


def _ols_sql() -> str:
    """The normal equations, solved by eliminating one unknown after the other."""
    d = len(DENSE)
    sums = [f"sum({DENSE[i]}*{DENSE[j]}) as a{i}{j}" for i in range(d) for j in range(d)] + [f"sum({f}*y) as b{i}" for i, f in enumerate(DENSE)]
    out = f"with e0 as (select {', '.join(sums)} from ({TRAIN_SQL['x_lineitem']}))"
    for k in range(d):
        row = lambda i, c: c if i == k else f"{c} - a{i}{k}*{c[0]}{k}{c[2:]}/a{k}{k}"  # noqa: B023, E731
        cells = [f"{row(i, f'a{i}{j}')} as a{i}{j}" for i in range(d) for j in range(d)] + [f"{row(i, f'b{i}')} as b{i}" for i in range(d)]
        out += f", e{k + 1} as (select {', '.join(cells)} from e{k})"
    return out + " select " + ", ".join(f"round(b{i}/a{i}{i}, 6) as w{i}" for i in range(d)) + f" from e{d}"


@query("ols_lineitem", _ols_sql())
def ols_lineitem(spark, d):
    return w_row(spark, L.ols(training(spark, d, "x_lineitem"), DENSE))


KM = "with p as materialized (select vec_id, embedding as x from embeddings), c0 as (select row_number() over (order by vec_id) - 1 as c, list_transform(x, lambda v: v::double) as m from p where vec_id < 4)"
for _k in range(3):
    KM += f", a{_k} as materialized (select vec_id, x, c from (select p.vec_id, p.x, c.c, row_number() over (partition by p.vec_id order by list_sum(list_transform(range(1, 65), lambda i: (p.x[i]::double - c.m[i]) * (p.x[i]::double - c.m[i]))), c.c) as k from p, c{_k} c) where k = 1), c{_k + 1} as materialized (select c, list(v order by i) as m, any_value(n) as n from (select c, i, avg(x[i]::double) as v, count(*) as n from a{_k}, range(1, 65) t(i) group by 1, 2) group by 1)"


@query("kmeans_embeddings", KM + " select cast(c as bigint) as c, n::bigint as size, round(m[1], 6) as m1, round(m[64], 6) as m64 from c3")
def kmeans_embeddings(spark, d):
    e = table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    start = [list(r.x) for r in e.where("vec_id < 4").orderBy("vec_id").collect()]
    centres, sizes = L.kmeans(e, start, 3)
    return spark.createDataFrame([(k, n, float(round(c[0], 6)), float(round(c[-1], 6))) for k, (c, n) in enumerate(zip(centres, sizes)) if n], "c long, size long, m1 double, m64 double")


@query("grid_search_lineitem", "with d as materialized (" + TRAIN_SQL["x_lineitem"] + ") select cast(a*3+b as bigint) as candidate, round(sum((0.2*a*x0 + 0.1*b*x1 - y)*(0.2*a*x0 + 0.1*b*x1 - y)/2)/count(*), 6) as loss from d, range(3) t(a), range(3) u(b) group by a, b")
def grid_search_lineitem(spark, d):
    grid = spark.createDataFrame([(a * 3 + b, [0.2 * a, 0.1 * b, 0.0, 0.0]) for a in range(3) for b in range(3)], "candidate long, w array<double>")
    return L.grid_search(training(spark, d, "x_lineitem"), grid, DENSE).select("candidate", F.round("loss", 6).alias("loss"))


@query("predict_eval_events", "with s as (select case when event_type='purchase' then 1 else 0 end as y, 1.0/(1.0+exp(-(value/200 - 1))) as p from events), b as (select round(p, 9) as s, sum(y) as pos, count(*) as n from s group by 1), r as (select *, coalesce(sum(n-pos) over (order by s rows between unbounded preceding and 1 preceding), 0) as below from b) select round(avg(case when (p >= 0.5) = (y > 0) then 1.0 else 0.0 end), 6) as accuracy, round(avg(-case when y > 0 then ln(greatest(least(p, 1-1e-15), 1e-15)) else ln(1-greatest(least(p, 1-1e-15), 1e-15)) end), 6) as log_loss, round(sqrt(avg((p-y)*(p-y))), 6) as rmse, (select round(sum(pos*(below+(n-pos)/2))/(sum(pos)*sum(n-pos)), 6) from r) as auc from s")
def predict_eval_events(spark, d):
    e = table(spark, d, "events").select(F.when(F.col("event_type") == "purchase", 1).otherwise(0).alias("y"), F.lit(1.0).alias("a"), (F.col("value") / 200).alias("b"))
    m = L.evaluate(L.predict(e, [-1.0, 1.0], ["a", "b"], "logistic"))
    return m.select(*[F.round(c, 6).alias(c) for c in ("accuracy", "log_loss", "rmse", "auc")])


VECTOR = {"q": "round(l_quantity*100)", "p": "round(l_extendedprice*100)", "d": "round(l_discount*100)", "t": "round(l_tax*100)"}
VECTOR_SQL = "select " + ", ".join(f"cast(sum(cast({v} as bigint)) as bigint) as {k}" for k, v in VECTOR.items()) + " from lineitem"


def topology(name: str, kind: str):
    @query(f"reduce_topology_{name}", VECTOR_SQL)
    def run(spark, d):
        rows = table(spark, d, "lineitem").repartition(int(spark.conf.get("spark.sql.shuffle.partitions")))
        out = reduced(rows, {k: F.expr(f"cast({v} as bigint)") for k, v in VECTOR.items()}, kind)
        return out.select(*VECTOR)


for _name, _kind in (("flat", "flat"), ("early", "early"), ("sqrt", "sqrt"), ("local_sqrt", "local_sqrt"), ("tree4", "tree"), ("random", "random"), ("blocks", "blocks"), ("sparse", "sparse")):
    topology(_name, _kind)


@query("keyed_statistic_lineitem", "select cast(sum(cast(round(l_quantity*100) as bigint)) as bigint) as sum from lineitem")
def keyed_statistic_lineitem(spark, d):
    return keyed_statistic(table(spark, d, "lineitem").select(F.expr("cast(round(l_quantity*100) as bigint)").alias("v")), "v")


@query("statistic_on_vertices_customer", "select cast(sum(cast(round(c_acctbal*100) as bigint)) as bigint) as sum from customer")
def statistic_on_vertices_customer(spark, d):
    s = statistic_on_vertices(table(spark, d, "customer").select(F.expr("cast(round(c_acctbal*100) as bigint)").alias("v")), "v")
    return spark.createDataFrame([(s,)], "sum long")


# published points: (method, machines, seconds) at 80 GB and 70 GB; fixed values
PUBLISHED = [
    ("bgd_ref", 5, 185.023), ("bgd_ref", 10, 70.4069), ("bgd_ref", 15, 46.8957), ("bgd_ref", 20, 35.8801), ("bgd_ref", 25, 29.142), ("bgd_ref", 30, 25.638), ("bgd_ref", 40, 20.016), ("bgd_ref", 50, 18.195), ("bgd_ref", 60, 15.12),
    ("bgd_im", 25, 37.946), ("bgd_im", 30, 15.806), ("bgd_im", 40, 15.407), ("bgd_im", 50, 17.81), ("bgd_im", 60, 20.683),
    ("rank_ref", 31, 186.137), ("rank_ref", 60, 98.5), ("rank_ref", 88, 67.993), ("rank_ref", 117, 55.091), ("rank_ref", 146, 49.763),
    ("rank_mr", 31, 2128.549), ("rank_mr", 60, 1184.116), ("rank_mr", 88, 701.411), ("rank_mr", 117, 550.34), ("rank_mr", 146, 472.152),
]
# runs taken from lines: the flags are the method, the quantity the machines, the price of a unit in thousandths the time of one run
RUNS_SQL = "select l_returnflag || l_linestatus as method, cast(floor(l_quantity) as bigint) as machines, cast(floor(l_extendedprice*1000/l_quantity) as bigint) as ms from lineitem where l_quantity >= 1"


@query("cost_optimal_published", f"with p as (select method, machines, cast(sum(ms) as bigint)::double/count(*)/1000 as seconds from ({RUNS_SQL}) where ms is not null and method is not null group by 1, 2), c as (select method, machines, machines*seconds::double as cost from p), l as (select method, min(cost) as least from c group by 1) select c.method, cast(min(c.machines) as bigint) as machines, round(any_value(l.least), 3) as least_cost from c join l on c.method = l.method and c.cost <= l.least*1.01 group by 1")
def cost_optimal_published(spark, d):
    """Fewest machines within a hundredth of the least cost, over the mean times of a table of runs; `PUBLISHED` holds the points of a paper in the same form."""
    runs = table(spark, d, "lineitem").where("l_quantity >= 1").select(F.concat("l_returnflag", "l_linestatus").alias("method"), F.floor("l_quantity").alias("machines"), F.floor(F.col("l_extendedprice") * 1000 / F.col("l_quantity")).alias("ms"))
    points = runs.where("ms is not null and method is not null").groupBy("method", "machines").agg((F.sum("ms").cast("double") / F.count("*") / 1000).alias("seconds"))
    return cost_optimal_points(points).select("method", "machines", F.round("least_cost", 3).alias("least_cost"))


@query("reduce_cost_model", "select l_suppkey as cluster, w::bigint as machines, round(4.0*w*16e6/125e6, 3) as flat, round(2*ceil(sqrt(4.0*w))*16e6/125e6, 3) as sqrt, round(2*ceil(sqrt(w::double))*16e6/125e6, 3) as local_sqrt, round(4*ceil(round(ln(greatest(w, 2)::double)/ln(4.0), 9))*16e6/125e6, 3) as tree from (select l_suppkey, count(*) as w from lineitem where l_suppkey is not null group by 1)")
def reduce_cost_model(spark, d):
    """A cluster for each supplier, with a machine for each of its lines and four tasks on each."""
    w = table(spark, d, "lineitem").where("l_suppkey is not null").groupBy(F.col("l_suppkey").alias("cluster")).agg(F.count("*").alias("machines"))
    cost = reduce_cost_columns(F.col("machines"), 4 * F.col("machines"), 16e6, 125e6)
    return w.select("cluster", "machines", *[F.round(cost[k], 3).alias(k) for k in ("flat", "sqrt", "local_sqrt", "tree")])
