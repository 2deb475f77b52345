"""Who sends what to whom. parts (layer, neuron, part): layer 0 owns the inputs, layer k the rows of matrix k."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .topology import BIAS


def send_map(weights: DataFrame, parts: DataFrame) -> DataFrame:
    """(layer, neuron, src, dst): the owner of input neuron of matrix layer, and each part with a row that reads it. src = dst stays in place.

    The constant input of a folded bias is known everywhere and has no route.
    """
    rows = parts.select("layer", F.col("neuron").alias("row"), F.col("part").alias("dst"))
    need = weights.filter(F.col("col") != BIAS).join(rows, ["layer", "row"]).select("layer", F.col("col").alias("neuron"), "dst").distinct()
    owners = parts.select((F.col("layer") + 1).alias("layer"), "neuron", F.col("part").alias("src"))
    return need.join(owners, ["layer", "neuron"]).select("layer", "neuron", "src", "dst")


def recv_map(routes: DataFrame) -> DataFrame:
    """What each part gets: the same rows, read from the receiving side."""
    return routes.select("layer", F.col("dst").alias("part"), F.col("src").alias("source"), "neuron")


def back_send_map(routes: DataFrame) -> DataFrame:
    """Backward, partial sums run the forward routes the other way."""
    return routes.select("layer", "neuron", F.col("dst").alias("src"), F.col("src").alias("dst"))


def back_recv_map(routes: DataFrame) -> DataFrame:
    return recv_map(back_send_map(routes))


def messages(routes: DataFrame) -> DataFrame:
    """(layer, src, dst, entries, words): one message a pair and layer."""
    return routes.filter("src <> dst").groupBy("layer", "src", "dst").agg(F.array_sort(F.collect_list("neuron")).alias("entries"), F.count(F.lit(1)).alias("words"))


def message_sizes(routes: DataFrame) -> DataFrame:
    """messages() of both passes without the entries."""
    one = routes.filter("src <> dst").groupBy("layer", "src", "dst").agg(F.count(F.lit(1)).alias("words"))
    return one.select("layer", F.lit("fwd").alias("pass"), "src", "dst", "words").unionByName(one.select("layer", F.lit("bwd").alias("pass"), F.col("dst").alias("src"), F.col("src").alias("dst"), "words"))
