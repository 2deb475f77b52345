"""Networks as (layer, row, col, w), their neuron lists, and layers derived from others."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import cut_lineage
from ..sources.generators import init_weights, mixed_radix
from ..sources.tables import read_table

BIAS = -1


@dataclass(frozen=True)
class Network:
    """weights (layer, row, col, w); neurons (layer, neuron) of layers 0 to depth, so that neurons without links are known too."""

    weights: DataFrame
    neurons: DataFrame
    depth: int
    activation: str = "sigmoid"

    def layer(self, k: int) -> DataFrame:
        return self.weights.filter(F.col("layer") == k).select("row", "col", "w")

    def of_layer(self, k: int) -> DataFrame:
        return self.neurons.filter(F.col("layer") == k).select("neuron")

    def with_weights(self, weights: DataFrame) -> Network:
        return Network(weights, self.neurons, self.depth, self.activation)


def trade_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """part <- customer, supplier <- part, nation <- supplier, region <- nation, as (layer, row, col)."""
    line = read_table(spark, sf_dir, "lineitem")
    orders = read_table(spark, sf_dir, "orders")
    one = line.join(orders, line.l_orderkey == orders.o_orderkey).select(F.col("l_partkey").alias("row"), F.col("o_custkey").alias("col")).distinct()
    two = line.select(F.col("l_suppkey").alias("row"), F.col("l_partkey").alias("col")).distinct()
    three = read_table(spark, sf_dir, "supplier").select(F.col("s_nationkey").cast("bigint").alias("row"), F.col("s_suppkey").alias("col"))
    four = read_table(spark, sf_dir, "nation").select(F.col("n_regionkey").cast("bigint").alias("row"), F.col("n_nationkey").cast("bigint").alias("col"))
    out = None
    for k, e in enumerate((one, two, three, four), 1):
        e = e.select(F.lit(k).alias("layer"), "row", "col")
        out = e if out is None else out.unionByName(e)
    return out


def trade_neurons(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for k, (name, key) in enumerate([("customer", "c_custkey"), ("part", "p_partkey"), ("supplier", "s_suppkey"), ("nation", "n_nationkey"), ("region", "r_regionkey")]):
        n = read_table(spark, sf_dir, name).select(F.lit(k).alias("layer"), F.col(key).cast("bigint").alias("neuron"))
        out = n if out is None else out.unionByName(n)
    return out


def trade_network(spark: SparkSession, sf_dir: str, activation: str = "sigmoid", form: str = "dyadic") -> Network:
    return Network(init_weights(trade_edges(spark, sf_dir), form=form), trade_neurons(spark, sf_dir), 4, activation)


def hour_network(spark: SparkSession, sf_dir: str, layers: int = 2, lag: int = 16, activation: str = "sigmoid") -> Network:
    """Hour <- the hours, its own and the lag - 1 before it, in which one of its users had an event too; every layer has these links."""
    seen = read_table(spark, sf_dir, "events").select("user_id", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600).cast("bigint").alias("row")).distinct()
    back = seen.select("user_id", "row", F.explode(F.sequence(F.col("row") - (lag - 1), F.col("row"))).alias("col"))
    links = cut_lineage(back.join(seen.withColumnRenamed("row", "col"), ["user_id", "col"]).select("row", "col").distinct())
    ks = F.explode(F.sequence(F.lit(1), F.lit(layers))).alias("layer")
    ids = links.select(F.col("row").alias("neuron")).distinct().select(F.explode(F.sequence(F.lit(0), F.lit(layers))).alias("layer"), "neuron")
    return Network(init_weights(links.select(ks, "row", "col")), ids, layers, activation)


def radix_network(spark: SparkSession, neurons: int, layers: int, degree: int, activation: str = "sigmoid", form: str = "dyadic", seed: int | None = None) -> Network:
    edges = mixed_radix(spark, neurons, layers, degree, seed)
    ids = spark.range(neurons).select(F.explode(F.sequence(F.lit(0), F.lit(layers))).alias("layer"), F.col("id").alias("neuron"))
    return Network(init_weights(edges, form=form), ids, layers, activation)


def fold_bias(weights: DataFrame, bias: DataFrame) -> DataFrame:
    """Bias (layer, row, b) as column BIAS of the weights; its input is the constant one, known to every part."""
    return weights.unionByName(bias.select("layer", "row", F.lit(BIAS).cast("bigint").alias("col"), F.col("b").alias("w")))


def conv_layer(spark: SparkSession, kernel: list[list[float]], height: int, width: int, stride: int = 1, pad: int = 0, ch_in: int = 1, ch_out: int = 1) -> DataFrame:
    """(row, col, w): a convolution as a sparse matrix. Neurons are channel * height * width + y * width + x; all channels share the kernel."""
    kh, kw = len(kernel), len(kernel[0])
    oh, ow = (height + 2 * pad - kh) // stride + 1, (width + 2 * pad - kw) // stride + 1
    taps = F.explode(F.array(*[F.struct(F.lit(c).alias("c"), F.lit(i).alias("i"), F.lit(j).alias("j"), F.lit(float(kernel[i][j])).alias("w")) for c in range(ch_in) for i in range(kh) for j in range(kw)])).alias("t")
    out = spark.range(ch_out * oh * ow).select(F.col("id").alias("row"), taps)
    y = (F.floor(F.col("row") / ow) % oh) * stride + F.col("t.i") - pad
    x = (F.col("row") % ow) * stride + F.col("t.j") - pad
    out = out.select("row", y.alias("y"), x.alias("x"), "t.c", "t.w").filter((F.col("y") >= 0) & (F.col("y") < height) & (F.col("x") >= 0) & (F.col("x") < width))
    return out.select("row", (F.col("c") * (height * width) + F.col("y") * width + F.col("x")).cast("bigint").alias("col"), "w")


def avg_pool_layer(spark: SparkSession, height: int, width: int, size: int = 2) -> DataFrame:
    """(row, col, w): the mean over size x size squares as a sparse matrix."""
    ow = width // size
    col = spark.range(height * width).select(F.col("id").alias("col"))
    row = F.floor(F.floor(F.col("col") / width) / size) * ow + F.floor((F.col("col") % width) / size)
    return col.select(row.cast("bigint").alias("row"), "col", F.lit(1.0 / (size * size)).alias("w"))


def max_pool(acts: DataFrame, width: int, size: int = 2) -> DataFrame:
    """acts (vec_id, neuron, x) pooled by maximum; not linear, hence an aggregate and no matrix."""
    ow = width // size
    to = F.floor(F.floor(F.col("neuron") / width) / size) * ow + F.floor((F.col("neuron") % width) / size)
    return acts.groupBy("vec_id", to.cast("bigint").alias("neuron")).agg(F.max("x").alias("x"))


def prune(weights: DataFrame, sparsity: float, scope: str = "layer", exact: bool = True) -> DataFrame:
    """Weights without the share sparsity of smallest magnitude, by layer or over the network.

    exact ranks (ties by row and column); else a percentile sketch sets the threshold, which needs no sort of all links.
    """
    if not exact:
        keys = ["layer"] if scope == "layer" else []
        cut = weights.groupBy(*keys).agg(F.percentile_approx(F.abs("w"), F.lit(float(sparsity)), F.lit(10000)).alias("cut"))
        joined = weights.join(F.broadcast(cut), keys) if keys else weights.crossJoin(F.broadcast(cut))  # one row a layer
        return joined.filter(F.abs("w") > F.col("cut")).select("layer", "row", "col", "w")
    over = Window.partitionBy("layer") if scope == "layer" else Window.partitionBy(F.lit(0))
    order = over.orderBy(F.abs("w"), "layer", "row", "col")
    ranked = weights.withColumn("nth", F.row_number().over(order)).withColumn("all", F.count(F.lit(1)).over(over))
    return ranked.filter(F.col("nth") > F.floor(F.col("all") * F.lit(float(sparsity)))).select("layer", "row", "col", "w")


def reachable(spark: SparkSession, weights: DataFrame, output_layer: int, output: int) -> DataFrame:
    """(layer, neuron) of the neurons that can affect one output, by a recursive query."""
    weights.select("layer", "row", "col").createOrReplaceTempView("reach_links")
    return spark.sql(f"""
        WITH RECURSIVE back(layer, neuron) AS (
            SELECT {output_layer}, CAST({output} AS BIGINT)
            UNION ALL
            SELECT b.layer - 1, l.col FROM back b JOIN (SELECT DISTINCT layer, row, col FROM reach_links) l ON l.layer = b.layer AND l.row = b.neuron
        ) SELECT DISTINCT layer, neuron FROM back""")
