"""Tables, derived graphs and training sets, and their SQL for the oracle.

Every fixture is a pure function of the given tables; see FIXTURES.md.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


HREFS = "href=[\"']([^\"']+)[\"']"

GRAPH_SQL = {
    "g_part_supp": "select distinct 2*l_partkey as src, 2*l_suppkey+1 as dst from lineitem union all select distinct 2*l_suppkey+1, 2*l_partkey from lineitem",
    "g_cust_part": "select distinct 2*o_custkey as src, 2*l_partkey+1 as dst from orders join lineitem on o_orderkey = l_orderkey",
    "g_pages": "select distinct 'p:' || page_id as src, 't:' || h as dst from (select page_id, unnest(regexp_extract_all(html, 'href=[\"'']([^\"'']+)[\"'']', 1)) as h from pages)",
    "g_turns": "select conv_id*1000+turn as src, nxt as dst from (select conv_id, turn, lead(conv_id*1000+turn) over (partition by conv_id order by turn) as nxt from conversations) where nxt is not null",
    "g_geo": "select cast(n_nationkey as bigint) as src, cast(100+n_regionkey as bigint) as dst from nation union all select cast(100+r_regionkey as bigint), cast(200 as bigint) from region",
    "g_user_next": "select event_type as src, nxt as dst, count(*) as weight from (select event_type, lead(event_type) over (partition by user_id order by ts, event_id) as nxt from events) where nxt is not null group by 1, 2",
}


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Edges (src, dst[, weight]) of a named graph."""
    t = lambda n: table(spark, sf_dir, n)
    if name == "g_part_supp":
        pairs = t("lineitem").select((2 * F.col("l_partkey")).alias("a"), (2 * F.col("l_suppkey") + 1).alias("b")).distinct()
        return pairs.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst")))).alias("e")).select("e.*")
    if name == "g_cust_part":
        both = t("orders").select("o_orderkey", "o_custkey").join(t("lineitem").select("l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
        return both.select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_partkey") + 1).alias("dst")).distinct()
    if name == "g_pages":
        links = t("pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit(HREFS), F.lit(1))).alias("h"))
        return links.select(F.concat(F.lit("p:"), F.col("page_id").cast("string")).alias("src"), F.concat(F.lit("t:"), "h").alias("dst")).distinct()
    if name == "g_turns":
        at = (F.col("conv_id") * 1000 + F.col("turn")).cast("long")
        steps = t("conversations").select(at.alias("src"), F.lead(at).over(Window.partitionBy("conv_id").orderBy("turn")).alias("dst"))
        return steps.where("dst is not null")
    if name == "g_geo":
        up = t("nation").select(F.col("n_nationkey").cast("long").alias("src"), (F.col("n_regionkey") + 100).cast("long").alias("dst"))
        return up.unionByName(t("region").select((F.col("r_regionkey") + 100).cast("long").alias("src"), F.lit(200).cast("long").alias("dst")))
    if name == "g_user_next":
        nxt = F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
        return t("events").select(F.col("event_type").alias("src"), nxt.alias("dst")).where("dst is not null").groupBy("src", "dst").agg(F.count("*").alias("weight"))
    raise KeyError(name)


TRAIN_SQL = {
    "x_lineitem": "select l_extendedprice/100000 as y, 1.0::double as x0, l_quantity/50 as x1, (l_discount+0)*10 as x2, (l_tax+0)*10 as x3 from lineitem",
    "x_events": "select event_id, case when event_type='purchase' then 1 else 0 end as y, unnest([0, 1 + user_id % 50, 51 + cast(json_extract_string(props,'$.k') as bigint) % 20, 71 + hour(ts)]) as f from events",
    "x_embed": "select vec_id, case when label=0 then 1.0 else -1.0 end as y, embedding as x from embeddings",
    "x_docs_tokens": "select doc_id, quality, tok, count(*) as n from (select d.doc_id, l.quality, unnest(string_split(lower(d.text), ' ')) as tok from documents d join labels l on d.doc_id = l.doc_id) where tok <> '' group by 1, 2, 3",
}


def training(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    if name == "x_lineitem":
        return t("lineitem").select(
            "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", (F.col("l_extendedprice") / 100000).alias("y"), F.lit(1.0).alias("x0"),
            (F.col("l_quantity") / 50).alias("x1"), ((F.col("l_discount") + 0) * 10).alias("x2"), ((F.col("l_tax") + 0) * 10).alias("x3"),
        )
    if name == "x_events":
        k = F.get_json_object("props", "$.k").cast("long")
        f = F.array(F.lit(0).cast("long"), 1 + F.col("user_id") % 50, 51 + k % 20, 71 + F.hour("ts").cast("long"))
        return t("events").select("event_id", F.when(F.col("event_type") == "purchase", 1).otherwise(0).alias("y"), f.alias("f"))
    if name == "x_embed":
        return t("embeddings").select("vec_id", F.when(F.col("label") == 0, 1.0).otherwise(-1.0).alias("y"), F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    if name == "x_docs_tokens":
        words = t("documents").join(t("labels"), "doc_id").select("doc_id", "quality", F.explode(F.split(F.lower("text"), " ")).alias("tok"))
        return words.where("tok <> ''").groupBy("doc_id", "quality", "tok").agg(F.count("*").alias("n"))
    raise KeyError(name)


def vertices(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


def adjacency(edges: DataFrame) -> DataFrame:
    """vertex (id, out): out-edges grouped by source, empty for sinks."""
    out = edges.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("out"))
    empty = F.array().cast(out.schema["out"].dataType)
    return vertices(edges).join(out, F.col("id") == F.col("src"), "left").select("id", F.coalesce("out", empty).alias("out"))


def edges_of(vertex: DataFrame) -> DataFrame:
    return vertex.select(F.col("id").alias("src"), F.explode("out").alias("dst"))


def duplicate_graph(edges: DataFrame, copies: int) -> DataFrame:
    """Disjoint copies: ids of copy i are shifted by i * (largest id + 1)."""
    top = edges.agg(F.max(F.greatest("src", "dst")).alias("top")).withColumn("top", F.coalesce("top", F.lit(0)))
    copy = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("i")
    moved = edges.join(F.broadcast(top)).select("*", copy)
    shift = F.col("i") * (F.col("top") + 1)
    return moved.withColumns({"src": F.col("src") + shift, "dst": F.col("dst") + shift}).drop("i", "top")


def duplicate_records(records: DataFrame, copies: int, seed: int = 0) -> DataFrame:
    """Copies with a copy number in the key, dealt out at random by a hash (the same on every run)."""
    many = records.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
    return many.repartition(F.xxhash64(*records.columns[:1], "copy", F.lit(seed)))


def read_adjacency_lines(spark: SparkSession, path: str) -> DataFrame:
    """vertex (id, out) from text lines `source target target ...`."""
    parts = F.split(F.trim("value"), r"\s+")
    return spark.read.text(path).where("trim(value) <> ''").select(parts[0].cast("long").alias("id"), F.transform(F.slice(parts, 2, F.size(parts)), lambda x: x.cast("long")).alias("out"))


def write_adjacency_lines(vertex: DataFrame, path: str) -> None:
    line = F.concat_ws(" ", F.col("id").cast("string"), F.transform("out", lambda x: x.cast("string")))
    vertex.select(line.alias("value")).write.text(path)


def read_any(spark: SparkSession, path: str, kind: str, schema: str | None = None, **options) -> DataFrame:
    """csv, json, orc, text or parquet."""
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(kind).load(path)


def write_any(df: DataFrame, path: str, kind: str, mode: str = "errorifexists", partition_by: list[str] | None = None, **options) -> None:
    w = df.write.mode(mode).options(**options).format(kind)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def bulk_load(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """An ordered store by primary key: a bucketed, sorted table. Joins on the key with an equally bucketed side need no exchange here."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)
    return df.sparkSession.table(name)
