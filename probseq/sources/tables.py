"""Sequence workloads on the given tables: (seq_id, pos, item), one row each, without probabilities.

Keys made of two numbers leave the second one all the room that it can take: days up to the year 2243, and as many
sentences as an array can hold.

Every builder reads only the columns it needs; keys and joins are arranged so that the small side decides first.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _number(by: str, *order: str):
    return F.row_number().over(Window.partitionBy(by).orderBy(*order))


def customer_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(seq_id, pos, orderkey, date): a customer's orders numbered by date and key; numbered before any join."""
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("seq_id"), F.col("o_orderkey").alias("orderkey"), F.col("o_orderdate").alias("date"))
    return o.withColumn("pos", _number("seq_id", "date", "orderkey"))


def _lines(spark: SparkSession, sf_dir: str, item) -> DataFrame:
    """Moved once: the distinct rows and a join by order use what lies by order."""
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), item.alias("item"))
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(part, "l_partkey")
    return line.select(F.col("l_orderkey").alias("orderkey"), "item").repartition("orderkey").distinct()


def customer_brand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer / order / brand."""
    return customer_orders(spark, sf_dir).join(_lines(spark, sf_dir, F.col("p_brand")), "orderkey").select("seq_id", "pos", "item")


def customer_type_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer / order / type and size class."""
    item = F.concat("p_type", F.floor(F.col("p_size") / 10).cast("string"))
    return customer_orders(spark, sf_dir).join(_lines(spark, sf_dir, item), "orderkey").select("seq_id", "pos", "item")


def segment_brand_type(spark: SparkSession, sf_dir: str, segment: str = "MACHINERY") -> DataFrame:
    """Customer of one segment / order / brand and type."""
    c = table(spark, sf_dir, "customer").where(F.col("c_mktsegment") == segment).select(F.col("c_custkey").alias("seq_id"))
    o = customer_orders(spark, sf_dir).join(c, "seq_id", "left_semi")
    return o.join(_lines(spark, sf_dir, F.concat("p_brand", "p_type")), "orderkey").select("seq_id", "pos", "item")


def order_brand(spark: SparkSession, sf_dir: str, tasks: int | None = None) -> DataFrame:
    """Order / ship date / brand; with `tasks` the rows lie by sequence in so many, moved once."""
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_brand").alias("item"))
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_shipdate").join(part, "l_partkey")
    day = F.datediff("l_shipdate", F.lit("1990-01-01").cast("date"))
    rows = line.select(F.col("l_orderkey").alias("seq_id"), day.alias("pos"), "item")
    return (rows if tasks is None else rows.repartition(tasks, "seq_id")).distinct()


def supplier_brand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier / ship month / brand, for patterns by region of the supplier."""
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), F.col("p_brand").alias("item"))
    line = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_partkey", "l_shipdate").join(part, "l_partkey")
    return line.select(F.col("l_suppkey").alias("seq_id"), (F.year("l_shipdate") * 12 + F.month("l_shipdate")).alias("pos"), "item").distinct()


def user_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User / event / event type: few, dense, long sequences."""
    e = table(spark, sf_dir, "events").select(F.col("user_id").alias("seq_id"), "ts", "event_id", F.col("event_type").alias("item"))
    return e.withColumn("pos", _number("seq_id", "ts", "event_id")).select("seq_id", "pos", "item")


def _user_days(spark: SparkSession, sf_dir: str, *more: str) -> DataFrame:
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", "event_type", *more)
    keyed = e.withColumn("seq_id", F.col("user_id").cast("long") * 100_000 + F.datediff("ts", F.lit("1970-01-01").cast("date")))
    return keyed.withColumn("pos", _number("seq_id", "ts", "event_id"))


def userday_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User and day / event / event type."""
    return _user_days(spark, sf_dir).select("seq_id", "pos", F.col("event_type").alias("item"))


def userday_clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User and day / event / event type with the tens digit of props.k: sparse."""
    tens = F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("string")
    return _user_days(spark, sf_dir, "props").select("seq_id", "pos", F.concat("event_type", tens).alias("item"))


def user_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User / six hours / set of event types."""
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_type")
    bucket = F.datediff("ts", F.lit("1970-01-01").cast("date")) * 4 + F.floor(F.hour("ts") / 6)
    return e.select(F.col("user_id").alias("seq_id"), bucket.cast("int").alias("pos"), F.col("event_type").alias("item")).distinct()


def _sentences(docs: DataFrame) -> DataFrame:
    """(seq_id, pos, item) of English documents: the words of each sentence, lower-cased."""
    s = docs.select("doc_id", F.posexplode(F.split(F.lower("text"), r"[.!?\n]")).alias("sentence", "body"))
    w = s.select((F.col("doc_id").cast("long") * (1 << 31) + F.col("sentence")).alias("seq_id"), F.filter(F.split("body", r"[^a-z]+"), lambda x: x != "").alias("words"))
    return w.select("seq_id", F.posexplode("words").alias("k", "item")).select("seq_id", (F.col("k") + 1).alias("pos"), "item")


def sentence_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sentences(table(spark, sf_dir, "documents").where(F.col("lang") == "en").select("doc_id", "text"))


def curated_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """English documents labelled good and not toxic that are no benchmark text themselves."""
    labels = table(spark, sf_dir, "labels")
    docs = table(spark, sf_dir, "documents").where(F.col("lang") == "en").select("doc_id", "text")
    good = labels.where("quality = 1").select("doc_id")
    bad = labels.where("toxic = 1").select("doc_id")
    return docs.join(good, "doc_id", "left_semi").join(bad, "doc_id", "left_anti").join(table(spark, sf_dir, "benchmark").select("text"), "text", "left_anti").select("doc_id", "text")


def curated_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sentences(curated_documents(spark, sf_dir))


def dialogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversation / turn / role and the distinct words."""
    c = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("seq_id"), F.col("turn").alias("pos"), "role", F.filter(F.split(F.lower("text"), r"[^a-z]+"), lambda x: x != "").alias("w"))
    words = F.array_distinct(F.concat(F.array(F.concat(F.lit("@"), "role")), "w"))
    return c.select("seq_id", "pos", F.explode(words).alias("item"))


def page_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page / place / tag name of the opening tags."""
    p = table(spark, sf_dir, "pages").select(F.col("page_id").alias("seq_id"), F.regexp_extract_all("html", F.lit(r"<([a-zA-Z][a-zA-Z0-9]*)"), F.lit(1)).alias("t"))
    return p.select("seq_id", F.posexplode("t").alias("k", "tag")).select("seq_id", (F.col("k") + 1).alias("pos"), F.lower("tag").alias("item"))


def vector_bins(spark: SparkSession, sf_dir: str, top: int = 3) -> DataFrame:
    """(seq_id, pos, item, p): label / vector / indexes of its largest components, p from their softmax share."""
    e = table(spark, sf_dir, "embeddings").where("label is not null and embedding is not null").select(F.col("label").cast("long").alias("seq_id"), F.col("vec_id").alias("pos"), "embedding")
    ranked = F.slice(F.reverse(F.array_sort(F.transform("embedding", lambda x, i: F.struct(F.round(F.exp(x.cast("double") * 4), 4).alias("v"), (-i).alias("i"))))), 1, top)
    r = e.select("seq_id", "pos", ranked.alias("r")).withColumn("s", F.aggregate("r", F.lit(0.0), lambda a, x: a + x["v"]))
    return r.select("seq_id", "pos", F.explode("r").alias("x"), "s").select("seq_id", "pos", F.concat(F.lit("c"), (-F.col("x.i")).cast("string")).alias("item"), F.round(F.col("x.v") / F.col("s"), 4).alias("p"))
