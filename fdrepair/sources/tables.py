"""Tables and wide views that the experiments run on. Schemas come from the files' footers; only the columns asked for are read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def orders_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with customer, nation and region; the dimension tables are small and Spark decides how to join them."""
    o, c, n, r = (table(spark, sf_dir, t) for t in ("orders", "customer", "nation", "region"))
    met = o.select(F.col("o_orderkey").alias("tid"), "o_custkey").join(c.select("c_custkey", "c_name", "c_nationkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
    met = met.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return met.select("tid", "o_custkey", "c_name", "c_nationkey", "n_name", "n_regionkey", "r_name", "c_mktsegment")


def customer_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    met = c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return met.select(F.col("c_custkey").alias("tid"), "c_custkey", "c_nationkey", "n_name", "n_regionkey", "r_name", "c_mktsegment")


LINE = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")


MOST_LINES = 1000  # of an order


def lineitem_wide(spark: SparkSession, sf_dir: str, numbered: bool = True) -> DataFrame:
    """Line items with part and supplier. numbered: ids are the order's key and the row's number in the order, the same in any
    engine; else a 64-bit hash of the row, which needs no order (ids may then collide; ``collisions`` counts them)."""
    line, p, s, n = (table(spark, sf_dir, t) for t in ("lineitem", "part", "supplier", "nation"))
    keyed = line.withColumn("tid", (F.col("l_orderkey") * MOST_LINES + F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*LINE))).cast("long") if numbered else F.abs(F.xxhash64(*LINE)))
    met = keyed.select("tid", "l_partkey", "l_suppkey").join(p.select("p_partkey", "p_name", "p_brand", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    met = met.join(s.select("s_suppkey", "s_name", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey")).join(n.select("n_nationkey", "n_name"), F.col("s_nationkey") == F.col("n_nationkey"))
    return met.select("tid", "l_partkey", "p_name", "p_brand", "p_type", "l_suppkey", "s_name", "s_nationkey", "n_name")


def customer_desk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with the desk that serves them, named by region and segment; its values hold the sign that joins left sides in texts."""
    return customer_wide(spark, sf_dir).select("tid", "n_name", "c_mktsegment", F.concat_ws("|", "r_name", "c_mktsegment").alias("desk"), "r_name", "c_nationkey")


def collisions(df: DataFrame, tid: str) -> DataFrame:
    """How many ids occur more than once."""
    return df.groupBy(tid).agg(F.count(F.lit(1)).alias("k")).where("k > 1").agg(F.count(F.lit(1)).alias("collisions"))


def replicated(df: DataFrame, times: int, tid: str, keys: tuple[str, ...]) -> DataFrame:
    """The table so many times over, with ids and key columns moved apart."""
    step = 10_000_000_000
    copies = df.sparkSession.range(times).withColumnRenamed("id", "__copy")
    met = df.crossJoin(F.broadcast(copies))  # a stated number of copies
    return met.select(*[(F.col(c) + F.col("__copy") * step).alias(c) if c in (tid, *keys) else F.col(c) for c in df.columns])


def pages_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "pages")
    host = F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1)
    return p.select(F.col("page_id").alias("tid"), host.alias("host"), F.regexp_extract("url", "^[a-z]+://[^/]+/([a-z]+)/", 1).alias("path_lang"), F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("html_lang"))


def documents_src(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("tid"), F.md5(F.col("text").cast("binary")).alias("digest"), "lang", "source", "n_chars")


def events_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.col("event_id").alias("tid"), "user_id", "event_type", F.get_json_object("props", "$.k").alias("k"))


def conv_role(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    return c.select((F.col("conv_id") * 1000 + F.col("turn")).alias("tid"), "turn", "role")


#: FD sets of the experiments.
CHAIN = "o_custkey -> c_nationkey; c_nationkey -> n_name; n_name -> n_regionkey; n_regionkey -> r_name"
CUSTOMER = "c_custkey -> c_nationkey; c_nationkey -> n_name; n_name -> c_nationkey; n_name -> r_name"
CUSTOMER_SCORED = "c_nationkey -> n_name; n_name -> c_nationkey; n_name -> r_name"
COMPOSITE = "n_name, c_mktsegment -> desk; desk -> r_name; desk, n_name -> c_nationkey"
LINES = "l_partkey -> p_brand; l_partkey -> p_type; l_suppkey -> s_nationkey; s_nationkey -> n_name"
CASE2 = "o_custkey -> r_name; c_nationkey -> r_name"
CYCLE = "c_name -> o_custkey; o_custkey -> c_name; o_custkey -> c_nationkey; c_nationkey -> n_name"
VIEWS = {"orders_wide": orders_wide, "customer_wide": customer_wide, "customer_desk": customer_desk, "lineitem_wide": lineitem_wide, "pages_lang": pages_lang, "documents_src": documents_src, "events_user": events_user, "conv_role": conv_role}
