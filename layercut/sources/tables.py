"""Readers with fixed schemas: columns are pruned and filters pushed by the scan."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WEIGHTS = "layer INT, row BIGINT, col BIGINT, w DOUBLE"
INPUTS = "vec_id BIGINT, neuron BIGINT, x DOUBLE"
TARGETS = "vec_id BIGINT, neuron BIGINT, y DOUBLE"
PARTS = "layer INT, neuron BIGINT, part INT"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_weights(weights: DataFrame, path: str) -> None:
    """Partitioned by layer: a pass over one layer reads that layer only."""
    weights.write.mode("overwrite").partitionBy("layer").parquet(path)


def read_layer(spark: SparkSession, path: str, layer: int | None = None) -> DataFrame:
    df = spark.read.schema(WEIGHTS).parquet(path).select("layer", "row", "col", "w")  # the layer comes from the folder, last
    return df if layer is None else df.filter(F.col("layer") == layer)


def write_blocks(weights: DataFrame, path: str) -> None:
    """Placed weights (with part) by layer and part: read_block touches the files of one block."""
    weights.write.mode("overwrite").partitionBy("layer", "part").parquet(path)


def read_block(spark: SparkSession, path: str, layer: int, part: int) -> DataFrame:
    return spark.read.parquet(path).filter((F.col("layer") == layer) & (F.col("part") == part))


def read_edges(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """Edge lists (row, col, w) in text; rows that don't parse are in bad, with the other columns null."""
    schema = "row BIGINT, col BIGINT, w DOUBLE, bad STRING"
    return spark.read.schema(schema).option("sep", sep).option("columnNameOfCorruptRecord", "bad").csv(path)


def write_edges(layer: DataFrame, path: str, sep: str = "\t") -> None:
    layer.select("row", "col", "w").write.mode("overwrite").option("sep", sep).csv(path)


def read_json_lines(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def write_any(df: DataFrame, path: str | None, fmt: str = "parquet") -> None:
    """fmt noop runs the plan without a sink, for timing."""
    writer = df.write.mode("overwrite").format(fmt)
    writer.save() if fmt == "noop" else writer.save(path)


def check_weights(weights: DataFrame) -> DataFrame:
    """Fails when read, on null or NaN entries; duplicate links are reported by duplicate_links()."""
    bad = F.col("layer").isNull() | F.col("row").isNull() | F.col("col").isNull() | F.col("w").isNull() | F.isnan("w")
    return weights.withColumn("w", F.when(bad, F.raise_error(F.lit("null or NaN weight")).cast("double")).otherwise(F.col("w")))


def duplicate_links(weights: DataFrame) -> DataFrame:
    return weights.groupBy("layer", "row", "col").agg(F.count(F.lit(1)).alias("times")).filter("times > 1")
