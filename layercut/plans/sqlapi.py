"""SQL text over a network: the views and the queries that give what the DataFrame API gives."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators.topology import Network


def register_views(spark: SparkSession, net: Network, parts: DataFrame | None = None, routes: DataFrame | None = None, prefix: str = "net") -> None:
    net.weights.createOrReplaceTempView(f"{prefix}_weights")
    net.neurons.createOrReplaceTempView(f"{prefix}_neurons")
    if parts is not None:
        parts.createOrReplaceTempView(f"{prefix}_parts")
    if routes is not None:
        routes.createOrReplaceTempView(f"{prefix}_routes")


def volume_sql(prefix: str = "net") -> str:
    return f"SELECT layer, 2 * count_if(src <> dst) AS words FROM {prefix}_routes GROUP BY layer"


def spmv_sql(layer: int, x_view: str, prefix: str = "net") -> str:
    return f"SELECT x.vec_id, w.row AS neuron, sum(w.w * x.x) AS z FROM {prefix}_weights w JOIN {x_view} x ON w.col = x.neuron WHERE w.layer = {layer} GROUP BY x.vec_id, w.row"
