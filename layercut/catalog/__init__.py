"""All queries of the engine and their DuckDB oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import cut_aware, encode, topology
from ..plans.sharded import Sharded, forward_sharded
from . import network, placement, relational, runs
from .base import ORACLES, QUERIES, P

__all__ = ["flagship", "network", "oracle_sql", "placement", "queries", "relational", "runs"]


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The trade network on cut-aware parts: each month's output for each region, and the words that the pass moves."""
    net = topology.trade_network(spark, sf_dir)
    sh = Sharded.of(net, cut_aware.multilevel_parts(net, P, trials=1), P)
    x = encode.trade_months(spark, sf_dir)
    out = forward_sharded(sh, x, x.select("vec_id").distinct())
    words = sh.routes.agg(F.count_if(F.col("src") != F.col("dst")).alias("words_per_vector"))
    return out.select("vec_id", F.col("neuron").alias("region"), "x").crossJoin(F.broadcast(words))  # one row
