"""The given tables and the workloads derived from them.

A workload is a set of frames: ``access`` (user, document, time), ``holding``
(distinct user and document) and ``doc_vectors`` (document, vector).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from semtrie.functions.vectors import as_double
from semtrie.plans.store import small

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, "
    "l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table with its fixed schema (no inference, no listing of footers)."""
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def events_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with the number in their JSON text as ``k``."""
    return table(spark, sf_dir, "events").withColumn("k", number_k(F.col("props")).cast("long"))


def number_k(props: Column) -> Column:
    """``$.k`` of a JSON text; one that is nothing but that number is not parsed."""
    alone = F.regexp_extract(props, r'^\{"k": *(0|[1-9][0-9]*)\}$', 1)
    return F.coalesce(F.nullif(alone, F.lit("")), F.get_json_object(props, "$.k"))


@dataclass(frozen=True)
class Workload:
    access: DataFrame
    doc_vectors: DataFrame

    @property
    def holding(self) -> DataFrame:
        return self.access.select("user_id", "doc_id").distinct()


def vectors_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("doc_id"), as_double(F.col("embedding")).alias("emb"))


def commerce(spark: SparkSession, sf_dir: str) -> Workload:
    """Customers and the parts they ordered; vectors are dealt to parts by number and carry no meaning."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_shipdate", "l_linenumber")
    access = lines.join(orders, lines.l_orderkey == orders.o_orderkey).select(
        F.col("o_custkey").alias("user_id"), F.col("l_partkey").alias("doc_id"), F.col("o_orderdate").alias("ts"), F.col("l_shipdate").alias("ts2"), F.col("l_orderkey").alias("tie"), F.col("l_linenumber").alias("tie2")
    )
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    count = vectors.agg(F.count(F.lit(1)).alias("n"))
    parts = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("doc_id")).crossJoin(F.broadcast(count))
    doc_vectors = parts.withColumn("vec_id", F.pmod("doc_id", "n")).join(vectors, "vec_id").select("doc_id", as_double(F.col("embedding")).alias("emb"))
    return Workload(access, doc_vectors)


def interest(spark: SparkSession, sf_dir: str) -> Workload:
    """Event users with planted interest groups: most events pick a vector of the user's pool, some from anywhere."""
    events = events_table(spark, sf_dir).select("event_id", "user_id", "ts", "event_type", "k")
    pool = table(spark, sf_dir, "embeddings").select("vec_id", "label")
    by_label = Window.partitionBy("label")
    pool = pool.withColumn("pos", F.row_number().over(by_label.orderBy("vec_id")) - 1).withColumn("n", F.count(F.lit(1)).over(by_label))
    sizes = pool.select("label", "n").distinct()
    picked = (
        events.filter(F.col("event_type").isin("view", "click", "purchase"))
        .withColumn("label", F.pmod("user_id", F.lit(10)))
        .join(F.broadcast(sizes), "label")  # one row per label
        .withColumn("pos", F.pmod("k", "n"))
        .join(small(pool.drop("n")), ["label", "pos"])
        .select("user_id", F.col("vec_id").alias("doc_id"), "ts", F.col("event_id").alias("tie"))
    )
    count = pool.agg(F.count(F.lit(1)).alias("total"))
    anywhere = (
        events.filter(F.col("event_type").isin("error", "signup"))
        .crossJoin(F.broadcast(count))  # a single row
        .select("user_id", (F.col("k") * F.expr("total DIV 100")).alias("doc_id"), "ts", F.col("event_id").alias("tie"))
    )
    return Workload(picked.unionByName(anywhere), vectors_table(spark, sf_dir))


def plain_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One user per vector: (user_id, n_docs, emb)."""
    return vectors_table(spark, sf_dir).select(F.col("doc_id").alias("user_id"), F.lit(1).cast("long").alias("n_docs"), "emb")


def normal_text(col: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(col), "[ \\t\\r\\n]+", " "))


def corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Document rows as held by (source, language) users; equal texts are one document."""
    d = table(spark, sf_dir, "documents")
    return d.select(F.concat_ws("/", "source", "lang").alias("user_id"), F.sha2(normal_text(F.col("text")), 256).alias("doc_id"), "lang", "text", F.col("doc_id").alias("row_id"))


def sites(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hosts as users, URLs as documents, page titles as text."""
    p = table(spark, sf_dir, "pages")
    return p.select(F.try_parse_url("url", F.lit("HOST")).alias("user_id"), F.col("url").alias("doc_id"), F.regexp_extract("html", "(?s)<title>(.*?)</title>", 1).alias("text"))


def chats(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(documents: assistant turns, queries: user turns) with the conversation as the user."""
    c = table(spark, sf_dir, "conversations")
    row = lambda role: c.filter(F.col("role") == role).select(F.col("conv_id").alias("user_id"), F.concat_ws(":", "conv_id", "turn").alias("doc_id"), "text")
    return row("assistant"), row("user").withColumnRenamed("doc_id", "query_id")


def passages(spark: SparkSession, sf_dir: str, words: int = 5) -> DataFrame:
    """(item_id, row_id) of the documents that contain a benchmark text.

    Items and documents meet on the hash of a run of words: the item's second to
    sixth (its first may begin inside a word), any of the document's.  Items too
    short to have them, at most a few, are compared directly.  The whole texts
    then decide.
    """
    split = lambda c: F.split(c, r"\s+")
    items = table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("item"), split(F.col("text")).alias("w"))
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    keyed = items.filter(F.size("w") >= words + 2).select("item_id", "item", F.xxhash64(F.array_join(F.slice("w", 2, words), " ")).alias("h"))
    runs = docs.select("doc_id", split(F.col("text")).alias("w")).filter(F.size("w") >= words)
    hashes = F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - words + 1), lambda i: F.xxhash64(F.array_join(F.slice("w", i, words), " "))))
    met = runs.select("doc_id", F.explode(hashes).alias("h")).join(keyed, "h").select("item_id", "item", "doc_id")
    found = met.join(docs, "doc_id").filter(F.contains("text", "item")).select("item_id", F.col("doc_id").alias("row_id"))
    short = items.filter(F.size("w") < words + 2).select("item_id", "item")
    direct = docs.join(short, F.contains("text", "item")).select("item_id", F.col("doc_id").alias("row_id"))
    return found.union(direct).distinct()
