"""Join and selection operators that Spark has no name for, as compositions of its own."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import portable_hash


def range_join(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, bin_size: float) -> DataFrame:
    """points whose value lies in [low, high): an equi-join on bins that a range covers, then the exact test; no nested loop."""
    left = points.withColumn("bin_no", F.floor(F.col(value) / bin_size))
    right = ranges.withColumn("bin_no", F.explode(F.sequence(F.floor(F.col(low) / bin_size), F.floor(F.col(high) / bin_size))))
    return left.join(right, "bin_no").filter((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("bin_no")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str, tie: str) -> DataFrame:
    """left with the value of the last right row of its key at or before its time (ties: the largest tie): one union and one window."""
    rows = left.withColumn("is_left", F.lit(1)).withColumn("got", F.lit(None).cast(right.schema[value].dataType)).withColumn("tie", F.lit(None).cast(right.schema[tie].dataType))
    other = right.select(key, ts, F.lit(0).alias("is_left"), F.col(value).alias("got"), F.col(tie).alias("tie"))
    both = rows.unionByName(other, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(ts, "is_left", "tie").rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn("last", F.last("got", ignorenulls=True).over(w)).filter("is_left = 1")
    return out.drop("is_left", "got", "tie").withColumnRenamed("last", value)


def shared_inputs(layer: DataFrame) -> DataFrame:
    """(a, b, shared): rows that read common inputs; used when rows are merged for coarsening, on layers of bounded fan-out."""
    a, b = layer.select("col", F.col("row").alias("a")), layer.select("col", F.col("row").alias("b"))
    return a.join(b, "col").filter("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"))


def heaviest_links(weights: DataFrame, k: int) -> DataFrame:
    """The k links of largest magnitude of each row."""
    w = Window.partitionBy("layer", "row").orderBy(F.desc(F.abs("w")), "col")
    return weights.withColumn("nth", F.row_number().over(w)).filter(F.col("nth") <= k).drop("nth")


def hash_sample(df: DataFrame, key: str, n: int, seed: int = 0) -> DataFrame:
    """n rows in hash order: the same on every run and engine."""
    return df.orderBy(portable_hash(F.col(key), "sample", seed), key).limit(n)


def threshold_image(pixels: Column) -> Column:
    """0/1 pixels by a pandas UDF, in Arrow batches. (Made when called: a UDF needs a running session.)"""

    @F.pandas_udf("array<int>")
    def run(values: pd.Series) -> pd.Series:
        return values.map(lambda v: None if v is None else [int(x is not None and x > 0) for x in v])

    return run(pixels)


def is_placed(df: DataFrame, column: Column) -> DataFrame:
    """(partition, value, n): which values lie in which partition, for checks of a placement."""
    return df.groupBy(F.spark_partition_id().alias("partition"), column.alias("value")).agg(F.count(F.lit(1)).alias("n"))
