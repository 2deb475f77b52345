"""Inputs (vec_id, neuron, x) and targets (vec_id, neuron, y) from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import portable_hash
from ..sources.tables import read_table

EVENT_TYPES = ["signup", "view", "purchase", "error", "click"]


def encode_images(vectors: DataFrame, side: int = 8, threshold: float = 0.0, base: int = 8) -> DataFrame:
    """Embeddings as base x base images, replicated to side x side, thresholded to 0/1 and flattened; zeros are left out."""
    times = side // base
    pixels = vectors.select("vec_id", F.posexplode("embedding").alias("at", "v")).filter(F.col("v") > threshold)
    pixels = pixels.select("vec_id", F.floor(F.col("at") / base).alias("y"), (F.col("at") % base).alias("x"))
    if times == 1:
        return pixels.select("vec_id", (F.col("y") * base + F.col("x")).cast("bigint").alias("neuron"), F.lit(1.0).alias("x"))
    step = F.sequence(F.lit(0), F.lit(times - 1))
    wide = pixels.select("vec_id", "y", "x", F.explode(step).alias("dy")).select("vec_id", "y", "x", "dy", F.explode(step).alias("dx"))
    at = (F.col("y") * times + F.col("dy")) * side + F.col("x") * times + F.col("dx")
    return wide.select("vec_id", at.cast("bigint").alias("neuron"), F.lit(1.0).alias("x"))


def one_hot_targets(vectors: DataFrame, label: str = "label") -> DataFrame:
    return vectors.select("vec_id", F.col(label).cast("bigint").alias("neuron"), F.lit(1.0).alias("y"))


def trade_months(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One vector a month since 1995-01; x = 1 for the customers that ordered in it."""
    o = read_table(spark, sf_dir, "orders")
    month = ((F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate") - 1).cast("bigint")
    return o.select(month.alias("vec_id"), F.col("o_custkey").alias("neuron")).distinct().withColumn("x", F.lit(1.0))


def trade_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """y = 1 for regions whose customers placed more than a fifth of the month's orders."""
    o, c, n = (read_table(spark, sf_dir, t) for t in ("orders", "customer", "nation"))
    month = ((F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate") - 1).cast("bigint")
    by = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey).groupBy(month.alias("vec_id"), F.col("n_regionkey").cast("bigint").alias("neuron")).agg(F.count(F.lit(1)).alias("n"))
    total = by.groupBy("vec_id").agg(F.sum("n").alias("total"))
    return by.join(total, "vec_id").filter("5 * n > total").select("vec_id", "neuron", F.lit(1.0).alias("y"))


def hashed_tokens(docs: DataFrame, bits: int = 10) -> DataFrame:
    """Bag of words in 2^bits buckets: x = 1 for the buckets of a document's lower-cased words."""
    word = F.explode(F.split(F.lower(F.coalesce("text", F.lit(""))), "[ \t\n\x0b\x0c\r]+")).alias("word")
    bucket = (portable_hash(F.col("word"), F.lit("token"), F.lit(0)) % (1 << bits)).alias("neuron")
    return docs.select(F.col("doc_id").alias("vec_id"), word).filter("word <> ''").select("vec_id", bucket).distinct().withColumn("x", F.lit(1.0))


def doc_targets(labels: DataFrame) -> DataFrame:
    """Neuron 0: quality, neuron 1: toxic."""
    both = F.explode(F.array(F.struct(F.lit(0).cast("bigint").alias("neuron"), F.col("quality").cast("double").alias("y")), F.struct(F.lit(1).cast("bigint").alias("neuron"), F.col("toxic").cast("double").alias("y")))).alias("t")
    return labels.select(F.col("doc_id").alias("vec_id"), both).select("vec_id", "t.neuron", "t.y")


def event_neuron():
    """event type * 24 + hour of the day."""
    return ((F.array_position(F.array(*map(F.lit, EVENT_TYPES)), F.col("event_type")) - 1) * 24 + F.hour("ts")).cast("bigint")


def event_windows(events: DataFrame) -> DataFrame:
    """One vector a user and day."""
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01")).cast("bigint")
    known = events.filter(F.col("event_type").isin(EVENT_TYPES))
    return known.select((F.col("user_id") * 1000 + day).alias("vec_id"), event_neuron().alias("neuron")).distinct().withColumn("x", F.lit(1.0))


def encode_pages(pages: DataFrame) -> DataFrame:
    """page_id, host, n_text, n_tags: plain features of raw pages."""
    bare = F.regexp_replace(F.coalesce("html", F.lit("")), "<[^>]*>", "")
    return pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.length(bare).cast("bigint").alias("n_text"), F.size(F.split("html", "<")).cast("bigint").alias("n_tags"))
