"""Generated layers: mixed-radix topologies, as DataFrames, as a Python data source and as a table function."""

from __future__ import annotations

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.hashing import dyadic_weight, uniform_weight


def strides(neurons: int, degree: int) -> list[int]:
    """1, d, d^2 ... below the number of neurons."""
    out = [1]
    while out[-1] * degree < neurons:
        out.append(out[-1] * degree)
    return out


def mixed_radix(spark: SparkSession, neurons: int, layers: int, degree: int, seed: int | None = None) -> DataFrame:
    """(layer, row, col): row r of layer k reads r + n * stride_k modulo neurons, n below degree. seed permutes the columns' ids."""
    steps = strides(neurons, degree)
    ks = F.explode(F.array(*[F.struct(F.lit(k + 1).alias("layer"), F.lit(steps[k % len(steps)]).cast("bigint").alias("stride")) for k in range(layers)])).alias("k")
    rows = spark.range(neurons).select(F.col("id").alias("row"), ks)
    rows = rows.select("k.layer", "row", "k.stride", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(degree - 1).cast("bigint"))).alias("n"))
    col = (F.col("row") + F.col("n") * F.col("stride")) % neurons
    if seed is not None:  # an affine permutation, co-prime with any power of two
        col = (col * (2 * seed + 1) + seed) % neurons
    return rows.select("layer", "row", col.alias("col"))


def init_weights(pattern: DataFrame, seed: int = 7, form: str = "dyadic") -> DataFrame:
    """pattern with w in [-1, 1], by a hash of the link: the same on every retry."""
    make = {"dyadic": dyadic_weight, "uniform": uniform_weight}[form]
    return pattern.withColumn("w", make(F.col("layer"), F.col("row"), F.col("col"), seed))


class _Rows(InputPartition):
    def __init__(self, first: int, past: int):
        self.first, self.past = first, past


class _RadixReader(DataSourceReader):
    def __init__(self, options):
        self.neurons, self.layers, self.degree = int(options.get("neurons", 64)), int(options.get("layers", 4)), int(options.get("degree", 8))
        self.splits = int(options.get("splits", 4))

    def partitions(self):
        size = -(-self.neurons // self.splits)
        return [_Rows(a, min(a + size, self.neurons)) for a in range(0, self.neurons, size)]

    def read(self, partition):
        steps = strides(self.neurons, self.degree)
        for k in range(self.layers):
            for r in range(partition.first, partition.past):
                for n in range(self.degree):
                    yield k + 1, r, (r + n * steps[k % len(steps)]) % self.neurons


class MixedRadixSource(DataSource):
    """spark.read.format('mixedradix').option('neurons', 64).option('layers', 4).option('degree', 8).load()"""

    @classmethod
    def name(cls):
        return "mixedradix"

    def schema(self):
        return "layer int, row bigint, col bigint"

    def reader(self, schema):
        return _RadixReader(self.options)


def register_generators(spark: SparkSession) -> None:
    """The data source, and the table functions mixed_radix_rows(neurons, degree, stride) and layer_fans(TABLE(links))."""
    from pyspark.sql.functions import udtf

    spark.dataSource.register(MixedRadixSource)

    @udtf(returnType="row bigint, col bigint")
    class RadixRows:
        def eval(self, neurons: int, degree: int, stride: int):
            for r in range(neurons):
                for n in range(degree):
                    yield r, (r + n * stride) % neurons

    @udtf(returnType="layer int, links bigint, widest bigint")
    class LayerFans:
        """Links of a layer and the most that one row has, from a table argument in the order of rows."""

        def __init__(self):
            self.layer, self.row, self.links, self.run, self.widest = None, None, 0, 0, 0

        def eval(self, link: Row):
            self.layer, self.links = link["layer"], self.links + 1
            self.run = self.run + 1 if link["row"] == self.row else 1
            self.row, self.widest = link["row"], max(self.widest, self.run)

        def terminate(self):
            if self.links:
                yield self.layer, self.links, self.widest

    spark.udtf.register("mixed_radix_rows", RadixRows)
    spark.udtf.register("layer_fans", LayerFans)
