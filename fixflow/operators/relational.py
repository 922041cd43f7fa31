"""The relational surface: scans, filters, joins, aggregates, windows, sorts, set operations and functions, each with its oracle."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import query
from ..sources.tables import HREFS, table, training

T = table


@query("scan_project_prune", "select l_orderkey, l_quantity from lineitem")
def scan_project_prune(spark, d):
    return T(spark, d, "lineitem").select("l_orderkey", "l_quantity")


@query("project_compute", "select l_orderkey, l_linenumber, round(l_extendedprice*(1-l_discount), 4) as net from lineitem")
def project_compute(spark, d):
    return T(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("filter_pushdown", "select l_orderkey, l_partkey, l_shipdate from lineitem where l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01' and l_quantity > 25")
def filter_pushdown(spark, d):
    on = (F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp")) & (F.col("l_shipdate") < F.lit("1996-01-01").cast("timestamp"))
    return T(spark, d, "lineitem").where(on & (F.col("l_quantity") > 25)).select("l_orderkey", "l_partkey", "l_shipdate")


@query("filter_null_state", "select o_orderkey, o_totalprice as state from orders where o_orderstatus <> 'F'")
def filter_null_state(spark, d):
    state = F.when(F.col("o_orderstatus") != "F", F.col("o_totalprice"))
    return T(spark, d, "orders").select("o_orderkey", state.alias("state")).where("state is not null")


@query("case_bucket", "select c_custkey, case when c_acctbal < 0 then 'debt' when c_acctbal < 5000 then 'low' else 'high' end as bucket from customer")
def case_bucket(spark, d):
    return T(spark, d, "customer").select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "low").otherwise("high").alias("bucket"))


@query("join_state_messages", "select p_partkey, round(p_retailprice + s, 4) as state from part join (select l_partkey, sum(l_quantity) as s from lineitem group by 1) on p_partkey = l_partkey")
def join_state_messages(spark, d):
    mail = T(spark, d, "lineitem").groupBy("l_partkey").agg(F.sum("l_quantity").alias("s"))
    return T(spark, d, "part").hint("merge").join(mail, F.col("p_partkey") == F.col("l_partkey")).select("p_partkey", F.round(F.col("p_retailprice") + F.col("s"), 4).alias("state"))


@query("cross_model", "select l_orderkey, l_linenumber, l_partkey, l_suppkey, round(0.5 + 2.0*l_quantity - 3.0*l_tax, 6) as score from lineitem")
def cross_model(spark, d):
    model = spark.createDataFrame([(0.5, 2.0, -3.0)], "b double, q double, t double")
    x = T(spark, d, "lineitem").crossJoin(F.broadcast(model))
    return x.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.col("b") + F.col("q") * F.col("l_quantity") + F.col("t") * F.col("l_tax"), 6).alias("score"))


_LATEST = "select o_custkey, o_orderkey, o_totalprice from (select *, row_number() over (partition by o_custkey order by o_orderdate desc, o_orderkey desc) as k from orders) where k = 1"


def _log(spark, d):
    return T(spark, d, "orders").select("o_custkey", "o_orderkey", "o_orderdate", "o_totalprice")


@query("latest_state_max_by", _LATEST)
def latest_state_max_by(spark, d):
    m = F.max_by(F.struct("o_orderkey", "o_totalprice"), F.struct("o_orderdate", "o_orderkey")).alias("m")
    return _log(spark, d).groupBy("o_custkey").agg(m).select("o_custkey", "m.o_orderkey", "m.o_totalprice")


@query("latest_state_join", _LATEST)
def latest_state_join(spark, d):
    log = _log(spark, d)
    last = log.groupBy("o_custkey").agg(F.max(F.struct("o_orderdate", "o_orderkey")).alias("m")).select("o_custkey", F.col("m.o_orderkey").alias("o_orderkey"))
    return log.join(last, ["o_custkey", "o_orderkey"]).select("o_custkey", "o_orderkey", "o_totalprice")


@query("latest_by_three_ways", f"select count(*) as customers, count(*) as agree from ({_LATEST})")
def latest_by_three_ways(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_orderdate"), F.desc("o_orderkey"))
    ranked = _log(spark, d).withColumn("k", F.row_number().over(w)).where("k = 1").select("o_custkey", F.col("o_orderkey").alias("a"))
    by, joined = latest_state_max_by(spark, d).select("o_custkey", F.col("o_orderkey").alias("b")), latest_state_join(spark, d).select("o_custkey", F.col("o_orderkey").alias("c"))
    same = (F.col("a") == F.col("b")) & (F.col("b") == F.col("c"))
    return ranked.join(by, "o_custkey").join(joined, "o_custkey").agg(F.count("*").alias("customers"), F.sum(same.cast("long")).alias("agree"))


@query("state_carry_over", "select c_custkey, round(coalesce(t, c_acctbal), 4) as state from customer left join (select o_custkey, sum(o_totalprice) as t from orders group by 1) on c_custkey = o_custkey")
def state_carry_over(spark, d):
    t = T(spark, d, "orders").groupBy("o_custkey").agg(F.sum("o_totalprice").alias("t"))
    return T(spark, d, "customer").join(t, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.round(F.coalesce("t", "c_acctbal"), 4).alias("state"))


@query("active_semi", "select c_custkey from customer where c_custkey in (select o_custkey from orders)")
def active_semi(spark, d):
    return T(spark, d, "customer").join(T(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("delta_anti", "select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey)")
def delta_anti(spark, d):
    return T(spark, d, "orders").join(T(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query("join_broadcast", "select n_name, round(sum(l_extendedprice), 2) as total from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey group by 1")
def join_broadcast(spark, d):
    s = T(spark, d, "supplier").select("s_suppkey", "s_nationkey")  # AQE broadcasts it where it is small; nation is a fixed 25 rows
    n = F.broadcast(T(spark, d, "nation").select("n_nationkey", "n_name"))
    x = T(spark, d, "lineitem").select("l_suppkey", "l_extendedprice").groupBy("l_suppkey").agg(F.sum("l_extendedprice").alias("p"))
    return x.join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(n, F.col("s_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.round(F.sum("p"), 2).alias("total"))


@query("join_shuffle_hash", "select o_orderkey, c_name from orders join customer on o_custkey = c_custkey")
def join_shuffle_hash(spark, d):
    return T(spark, d, "orders").join(T(spark, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name")


@query("join_full_outer", "select c_custkey, o_orderkey from customer full join orders on c_custkey = o_custkey")
def join_full_outer(spark, d):
    return T(spark, d, "customer").join(T(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "full").select("c_custkey", "o_orderkey")


@query("join_theta_band", "select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_suppkey < b.s_suppkey and abs(a.s_acctbal - b.s_acctbal) <= 20")
def join_theta_band(spark, d):
    """A band join as an equi-join on the band's number: each row meets its own band and the next."""
    s = T(spark, d, "supplier").select("s_suppkey", "s_acctbal").withColumn("band", F.floor(F.col("s_acctbal") / 20))
    near = s.select(F.col("s_suppkey").alias("k2"), F.col("s_acctbal").alias("v2"), F.explode(F.array(F.col("band") - 1, "band", F.col("band") + 1)).alias("band"))
    x = s.join(near, "band").where((F.col("s_suppkey") < F.col("k2")) & (F.abs(F.col("s_acctbal") - F.col("v2")) <= 20))
    return x.select(F.col("s_suppkey").alias("a"), F.col("k2").alias("b"))


@query("join_asof_events", "select p.event_id, (select max_by(c.event_id, (c.ts, c.event_id)) from events c where c.event_type='click' and c.user_id = p.user_id and (c.ts < p.ts or (c.ts = p.ts and c.event_id < p.event_id))) as click_id from events p where p.event_type = 'purchase'")
def join_asof_events(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    x = T(spark, d, "events").where("event_type in ('click', 'purchase')").withColumn("click_id", F.last(click, ignorenulls=True).over(w))
    return x.where("event_type = 'purchase'").select("event_id", "click_id")


@query("join_interval_events", "select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour where c.event_type='click' and p.event_type='purchase'")
def join_interval_events(spark, d):
    """Equal user and hour bucket (own and next), then the exact range."""
    e = T(spark, d, "events").select("event_id", "user_id", "event_type", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000).alias("hour"))
    c = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("t"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    p = e.where("event_type = 'purchase'").select("user_id", "hour", F.col("event_id").alias("purchase_id"), "ts")
    return c.join(p, ["user_id", "hour"]).where("ts >= t and ts <= t + interval 1 hour").select("click_id", "purchase_id")


_BY_SUPP = "select l_suppkey, count(*) as n, round(sum(l_quantity), 4) as q from lineitem group by 1"


@query("agg_two_phase", _BY_SUPP)
def agg_two_phase(spark, d):
    return T(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("q"))


@query("agg_sort_based", _BY_SUPP)
def agg_sort_based(spark, d):
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    x = T(spark, d, "lineitem").select("l_suppkey", "l_quantity").repartition(n, "l_suppkey").sortWithinPartitions("l_suppkey")
    return x.groupBy("l_suppkey").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("q"))


@query("agg_global", "select count(*) as n, round(sum(l_extendedprice), 2) as total, round(avg(l_quantity), 6) as q, min(l_shipdate) as first, max(l_shipdate) as last from lineitem")
def agg_global(spark, d):
    return T(spark, d, "lineitem").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"), F.round(F.avg("l_quantity"), 6).alias("q"), F.min("l_shipdate").alias("first"), F.max("l_shipdate").alias("last"))


@query("agg_distinct", "select l_partkey, count(distinct l_suppkey) as suppliers from lineitem group by 1")
def agg_distinct(spark, d):
    return T(spark, d, "lineitem").groupBy("l_partkey").agg(F.count_distinct("l_suppkey").alias("suppliers"))


@query("agg_conditional", "select user_id, count(*) filter (event_type='click') as clicks, count(*) filter (event_type='purchase') as purchases from events group by 1")
def agg_conditional(spark, d):
    c = lambda t: F.sum(F.when(F.col("event_type") == t, 1).otherwise(0))
    return T(spark, d, "events").groupBy("user_id").agg(c("click").alias("clicks"), c("purchase").alias("purchases"))


@query("agg_rollup", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by rollup(o_orderstatus, o_orderpriority)")
def agg_rollup(spark, d):
    return T(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("agg_cube", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by cube(o_orderstatus, o_orderpriority)")
def agg_cube(spark, d):
    return T(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("agg_grouping_sets", "select c_nationkey, c_mktsegment, grouping(c_nationkey) as gn, grouping(c_mktsegment) as gs, count(*) as n from customer group by grouping sets ((c_nationkey), (c_mktsegment), ())")
def agg_grouping_sets(spark, d):
    c = T(spark, d, "customer")
    return spark.sql(
        "select c_nationkey, c_mktsegment, cast(grouping(c_nationkey) as bigint) as gn, cast(grouping(c_mktsegment) as bigint) as gs, count(*) as n from {c} group by grouping sets ((c_nationkey), (c_mktsegment), ())", c=c
    )


@query("win_rank", "select p_partkey, row_number() over w as rn, rank() over v as rk, dense_rank() over v as dr, ntile(4) over w as nt from part window w as (partition by p_brand order by p_retailprice, p_partkey), v as (partition by p_brand order by p_retailprice)")
def win_rank(spark, d):
    w, v = Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_retailprice")
    c = lambda f, o, n: f.over(o).cast("long").alias(n)
    return T(spark, d, "part").select("p_partkey", c(F.row_number(), w, "rn"), c(F.rank(), v, "rk"), c(F.dense_rank(), v, "dr"), c(F.ntile(4), w, "nt"))


def _user(spark, d):
    return T(spark, d, "events"), Window.partitionBy("user_id").orderBy("ts", "event_id")


@query("win_lag_events", "select event_id, lag(event_type) over w as prev, lead(event_type) over w as nxt from events window w as (partition by user_id order by ts, event_id)")
def win_lag_events(spark, d):
    e, w = _user(spark, d)
    return e.select("event_id", F.lag("event_type").over(w).alias("prev"), F.lead("event_type").over(w).alias("nxt"))


@query("win_moving_avg", "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 6) as m from events")
def win_moving_avg(spark, d):
    e, w = _user(spark, d)
    return e.select("event_id", F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 6).alias("m"))


@query("win_running_sum", "select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows unbounded preceding), 4) as s from events")
def win_running_sum(spark, d):
    e, w = _user(spark, d)
    return e.select("event_id", F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("s"))


@query("win_range_frame", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as n from events")
def win_range_frame(spark, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return T(spark, d, "events").select("event_id", F.count("*").over(w).alias("n"))


@query("sort_within_partitions", "select count(*) as n, cast(0 as bigint) as descents from lineitem")
def sort_within_partitions(spark, d):
    """Rows of each task in order: counts neighbours out of order, found per task."""
    x = T(spark, d, "lineitem").select("l_orderkey").repartition("l_orderkey").sortWithinPartitions("l_orderkey")

    def descents(batches):
        n, bad, last = 0, 0, None
        for b in batches:
            v = b.column(0).to_numpy()
            if len(v):
                bad += int((v[1:] < v[:-1]).sum()) + (last is not None and v[0] < last)
                n, last = n + len(v), v[-1]
        yield pa.RecordBatch.from_pydict({"n": [n], "bad": [bad]})

    return x.mapInArrow(descents, "n long, bad long").agg(F.sum("n").alias("n"), F.sum("bad").alias("descents"))


def _keys(spark, d):
    return T(spark, d, "lineitem").select(F.col("l_partkey").alias("k")), T(spark, d, "supplier").select(F.col("s_suppkey").alias("k"))


@query("set_union", "select l_partkey as k from lineitem union select s_suppkey from supplier")
def set_union(spark, d):
    a, b = _keys(spark, d)
    return a.union(b).distinct()


@query("set_union_all", "select p_partkey as k from part union all select s_suppkey from supplier")
def set_union_all(spark, d):
    return T(spark, d, "part").select(F.col("p_partkey").alias("k")).unionAll(_keys(spark, d)[1])


@query("set_intersect", "select l_partkey as k from lineitem intersect select s_suppkey from supplier")
def set_intersect(spark, d):
    a, b = _keys(spark, d)
    return a.intersect(b)


@query("set_except", "select l_partkey as k from lineitem except select s_suppkey from supplier")
def set_except(spark, d):
    a, b = _keys(spark, d)
    return a.subtract(b)


@query("set_except_all", "select c_nationkey as k from customer except all select s_nationkey from supplier")
def set_except_all(spark, d):
    return T(spark, d, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(T(spark, d, "supplier").select(F.col("s_nationkey").alias("k")))


@query("fn_array_dot", "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 6) as norm2, round(list_sum(list_transform(embedding[1:8], lambda x: x::double)), 6) as head from embeddings")
def fn_array_dot(spark, d):
    v = F.transform("embedding", lambda x: x.cast("double"))
    add = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    return T(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(v, v, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x), 6).alias("norm2"), F.round(add(F.slice(v, 1, 8)), 6).alias("head"))


@query("fn_array_zip_add", "select a.vec_id, round(list_sum(list_transform(range(1, 65), lambda i: a.embedding[i]::double + b.embedding[i]::double)), 5) as s from embeddings a join embeddings b on b.vec_id = a.vec_id + 1")
def fn_array_zip_add(spark, d):
    e = T(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("u"))
    b = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("u").alias("v"))
    return e.join(b, "vec_id").select("vec_id", F.round(F.aggregate(F.zip_with("u", "v", lambda x, y: x + y), F.lit(0.0), lambda s, x: s + x), 5).alias("s"))


_LINKS = "regexp_extract_all(html, 'href=[\"'']([^\"'']+)[\"'']', 1)"


@query("fn_explode_links", f"select page_id, unnest({_LINKS}) as href from pages")
def fn_explode_links(spark, d):
    return T(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(HREFS), F.lit(1))).alias("href"))


@query("fn_links", f"select page_id, cast(len({_LINKS}) as bigint) as links, lower(url) as url from pages")
def fn_links(spark, d):
    return T(spark, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit(HREFS), F.lit(1))).cast("long").alias("links"), F.lower("url").alias("url"))


@query("fn_map_sparse", "select f as feature, count(*) as n from (select unnest([0, 1 + user_id % 50, 51 + cast(json_extract_string(props,'$.k') as bigint) % 20, 71 + hour(ts)]) as f from events) group by 1")
def fn_map_sparse(spark, d):
    """Sparse vectors as maps, back to entries."""
    x = training(spark, d, "x_events").select(F.map_from_arrays("f", F.transform("f", lambda _: F.lit(1.0))).alias("m"))
    return x.select(F.explode(F.map_entries("m")).alias("e")).groupBy(F.col("e.key").alias("feature")).agg(F.count("*").alias("n"))


@query("fn_tokens", "select tok, count(*) as n from (select unnest(string_split(lower(d.text), ' ')) as tok from documents d join labels l on d.doc_id = l.doc_id) where tok <> '' group by 1")
def fn_tokens(spark, d):
    x = T(spark, d, "documents").select("doc_id", "text").join(T(spark, d, "labels").select("doc_id"), "doc_id")
    return x.select(F.explode(F.split(F.lower("text"), " ")).alias("tok")).where("tok <> ''").groupBy("tok").agg(F.count("*").alias("n"))


@query("fn_json_props", "select event_id, cast(json_extract_string(props,'$.k') as bigint) as k from events")
def fn_json_props(spark, d):
    return T(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("fn_date_parts", "select event_id, hour(ts) as h, date_trunc('day', ts)::timestamp as day, epoch_us(ts) as us from events")
def fn_date_parts(spark, d):
    return T(spark, d, "events").select("event_id", F.hour("ts").cast("long").alias("h"), F.date_trunc("day", "ts").alias("day"), F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))


@query("fn_math", "select event_id, round(exp(-value/1000), 6) as e, round(ln(1+abs(value)), 6) as l, round(sqrt(abs(value)), 6) as r, cast(sign(value) as bigint) as s from events")
def fn_math(spark, d):
    v = F.col("value")
    return T(spark, d, "events").select("event_id", F.round(F.exp(-v / 1000), 6).alias("e"), F.round(F.log1p(F.abs(v)), 6).alias("l"), F.round(F.sqrt(F.abs(v)), 6).alias("r"), F.signum(v).cast("long").alias("s"))


@query("udf_arrow_map_partials", "select count(*) as n, round(sum(l_extendedprice), 2) as total from lineitem")
def udf_arrow_map_partials(spark, d):
    """A statistic by an Arrow batch function: one partial row a task, then one global sum."""

    def partial(batches):
        n, s = 0, 0.0
        for b in batches:
            n, s = n + len(b), s + float(b.column(0).to_numpy().sum())
        yield pa.RecordBatch.from_pydict({"n": [n], "s": [s]})

    return T(spark, d, "lineitem").select("l_extendedprice").mapInArrow(partial, "n long, s double").agg(F.sum("n").alias("n"), F.round(F.sum("s"), 2).alias("total"))


@query("udaf_grouped_sum", "select l_returnflag, round(sum(l_quantity*l_tax), 4) as s from lineitem group by 1")
def udaf_grouped_sum(spark, d):
    """A grouped pandas aggregate over partial sums, so that groups stay small."""

    @F.pandas_udf("double")
    def total(v: pd.Series) -> float:
        return float(v.sum())

    part = T(spark, d, "lineitem").groupBy("l_returnflag", "l_linenumber").agg(F.sum(F.col("l_quantity") * F.col("l_tax")).alias("p"))
    return part.groupBy("l_returnflag").agg(F.round(total("p"), 4).alias("s"))


@query("udtf_members", f"select page_id, cast(i as bigint) as pos, href from (select page_id, unnest({_LINKS}) as href, generate_subscripts({_LINKS}, 1) - 1 as i from pages)")
def udtf_members(spark, d):
    @F.udtf(returnType="pos long, href string")
    class Members:
        def eval(self, links):
            for i, x in enumerate(links or []):
                yield i, x

    pages = T(spark, d, "pages").select("page_id", F.regexp_extract_all("html", F.lit(HREFS), F.lit(1)).alias("links"))
    return pages.lateralJoin(Members(F.col("links").outer())).select("page_id", "pos", "href")


@query("stats_single_round", "select min(l_extendedprice) as min, max(l_extendedprice) as max, round(sum(l_extendedprice), 2) as sum, count(l_extendedprice) as count, round(avg(l_extendedprice), 4) as mean, round(var_samp(l_extendedprice), 2) as var from lineitem")
def stats_single_round(spark, d):
    from .mru import stat_query

    s = stat_query(T(spark, d, "lineitem"), "l_extendedprice")
    return s.select("min", "max", F.round("sum", 2).alias("sum"), "count", F.round("mean", 4).alias("mean"), F.round("var", 2).alias("var"))


