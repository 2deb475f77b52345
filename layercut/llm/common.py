"""Helpers shared by the corpus operators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import cut_lineage

__all__ = ["HOT_SHARE", "WHITE", "cut_lineage", "join_spread", "lower_ascii", "small_or_shuffled", "spread", "squash_white", "table", "words"]

#: Rows of a few numbers each that are broadcast; more are joined by a shuffle.
BROADCAST_ROWS = 1_000_000
#: Keys of more than this share of all rows are joined by a broadcast: there are at most 1 / HOT_SHARE of them.
HOT_SHARE = 0.001

# The six white-space characters that part words (0x20, 0x09 to 0x0D).
WHITE = "\t\n\x0b\x0c\r"
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def squash_white(text: Column) -> Column:
    """Null becomes empty, and each white-space character a blank; literal replaces stay in generated code."""
    text = F.coalesce(text, F.lit(""))
    for c in WHITE:
        text = F.replace(text, F.lit(c), F.lit(" "))
    return text


def words(text: Column) -> Column:
    """Maximal runs of other characters than white space."""
    return F.array_remove(F.split(squash_white(text), " "), "")


def lower_ascii(text: Column) -> Column:
    return F.translate(text, _UPPER, _UPPER.lower())


def spread(rows: int, per_bucket: int) -> int:
    """Number of buckets that hold about per_bucket rows each."""
    return max(1, -(-rows // per_bucket))


def small_or_shuffled(rows: DataFrame) -> DataFrame:
    """rows (a checkpoint), to be broadcast where they are at most BROADCAST_ROWS."""
    return F.broadcast(rows) if rows.count() <= BROADCAST_ROWS else rows


def join_spread(rows: DataFrame, side: DataFrame, keys: list[str], copies: str, total: int) -> DataFrame:
    """rows left-joined with side (a checkpoint with one row a key). copies: how many of the total rows have the key; keys of many rows
    are broadcast, so that none gathers in one task."""
    hot = F.broadcast(side.filter(F.col(copies) > F.lit(HOT_SHARE * total)))
    rest = side.filter(F.col(copies) <= F.lit(HOT_SHARE * total)).hint("merge")
    return rows.join(hot, keys).unionByName(rows.join(hot, keys, "left_anti").join(rest, keys, "left"))
