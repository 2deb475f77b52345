"""Operator 9: mixing sources to target weights by pivotal dependent rounding.

Every document of a source gets the same expected number of copies, target / source size. The whole part is given outright; the
fractional parts are paired, and words are moved at random from one document of a pair to the other until one of the two is
integral. A move keeps the words of the pair, so a source's taken words differ from its target by less than one document.
Groups are (source, hash bucket); each leaves one fractional document and its smallest ones, as many as together weigh HELD_WEIGHT times its
largest, and these residuals meet in a reduction tree, so a source that holds most rows is never gathered in one task. At the root
those held back take up what the last, large residual lacks, so that what is left over is a part of a small document.

Defined results: null text has size 0; a null source is a source of its own, the last; documents of size 0 are rounded on their
own (they add no words); repeated rows are rounded as rows of their own; an empty table gives an empty result. The draws depend on
the source, the bucket and the rows only, so that reruns agree.
"""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut_lineage, spread, words

#: Rows of a leaf group and residuals of an inner node of the reduction tree.
LEAF_ROWS, FAN_IN = 512, 32
#: Words of the documents that a group passes on besides its residual, as a multiple of its largest open document.
HELD_WEIGHT = 4
#: Sources that one task puts in order.
SOURCE_ROWS = 100_000
#: Sources up to this many are broadcast to the documents; more are joined by a shuffle.
BROADCAST_SOURCES = 100_000
_SCHEMA = "doc_id long, row_key long, source string, size long, source_size long, target double, base int, part double, bucket int, copies int"


def _numbered(per: DataFrame) -> DataFrame:
    """per with nth, the place of its source in code-point order (null last): ordered by ranges, each counted on from those before it."""
    ranges = spread(per.count(), SOURCE_ROWS)
    at = per.repartitionByRange(ranges, F.col("source").asc_nulls_last()).sortWithinPartitions(F.col("source").asc_nulls_last()).withColumn("at", F.monotonically_increasing_id())
    at = cut_lineage(at.withColumn("range", F.shiftright("at", 33)).withColumn("at", F.col("at").bitwiseAND(F.lit((1 << 33) - 1))))
    before = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # one row a range
    ahead = at.groupBy("range").agg(F.count(F.lit(1)).alias("n")).select("range", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("ahead"))
    return at.join(F.broadcast(ahead), "range").withColumn("nth", F.col("at") + F.col("ahead")).drop("at", "range", "ahead")


def source_targets(sized: DataFrame, cap: float = 3.0) -> DataFrame:
    """(source, source_size, target): weights 1, 2, 3 repeating in code-point order, shares of all words, stopped at cap times the size.

    Each round shares what the stopped sources leave among the others by weight and stops those above; one sum over the sources a round.
    """
    per = cut_lineage(sized.groupBy("source").agg(F.sum("size").alias("source_size")))
    per = _numbered(per).withColumn("weight", F.col("nth") % 3 + 1).withColumn("most", F.col("source_size") * F.lit(float(cap)))
    per = cut_lineage(per.withColumn("stop", F.col("most") / F.col("weight")))
    everything = per.agg(F.sum("source_size")).first()[0] or 0
    level, stopped = 0.0, None
    while True:
        now = per.agg(F.sum(F.when(F.col("stop") <= level, F.col("most"))).alias("held"), F.sum(F.when(F.col("stop") > level, F.col("weight"))).alias("weight"), F.count_if(F.col("stop") <= level).alias("n")).first()
        if not now["weight"] or now["n"] == stopped:
            break
        level, stopped = (everything - (now["held"] or 0.0)) / now["weight"], now["n"]
    return per.select("source", "source_size", F.least("most", F.lit(float(level)) * F.col("weight")).alias("target"))


def settle(sizes: np.ndarray, parts: np.ndarray, draw: np.random.Generator) -> np.ndarray:
    """Parts after pairing in the given order: all are 0 or 1 but for one at most."""
    out = parts.astype(float).copy()
    open_ = -1
    for j in range(len(out)):
        if not 0.0 < out[j] < 1.0:
            continue
        if open_ < 0:
            open_ = j
            continue
        i, si, sj = open_, float(sizes[open_]), float(sizes[j])
        a, b = out[i] * si, out[j] * sj
        to_j, to_i = min(a, sj - b), min(b, si - a)
        if draw.random() * (to_i + to_j) < to_i:
            i_done, j_done = (a <= sj - b), (sj - b <= a)
            out[i], out[j] = (0.0 if i_done else (a - to_j) / si), (1.0 if j_done else (b + to_j) / sj)
        else:
            i_done, j_done = (si - a <= b), (b <= si - a)
            out[i], out[j] = (1.0 if i_done else (a + to_i) / si), (0.0 if j_done else (b - to_i) / sj)
        open_ = j if 0.0 < out[j] < 1.0 else i if 0.0 < out[i] < 1.0 else -1
    return out


def finish(sizes: np.ndarray, parts: np.ndarray, draw: np.random.Generator) -> np.ndarray:
    """Parts, all 0 or 1, for documents in falling order of size: each is driven to one end, drawn once, by those after it (to the other
    end where those after it can't give or take enough for the end drawn).

    Pairing leaves the largest document of a set fractional; the few held back for this step take up what it lacks, so that the
    last one open is a small one.
    """
    out, open_, up = parts.astype(float).copy(), -1, False
    live = (out > 0) & (out < 1)
    after = lambda x: np.append(np.cumsum(np.where(live, x, 0.0)[::-1])[::-1][1:], 0.0)
    gives, takes = after(out * sizes), after((1 - out) * sizes)  # words of all that come later
    for j in range(len(out)):
        if not 0.0 < out[j] < 1.0:
            continue
        if open_ >= 0:
            i, si, sj = open_, float(sizes[open_]), float(sizes[j])
            lacks, has = ((1 - out[i]) * si, out[j] * sj) if up else (out[i] * si, (1 - out[j]) * sj)
            if has < lacks:
                out[i] += has / si * (1 if up else -1)
                out[j] = 0.0 if up else 1.0
                continue
            out[i] = 1.0 if up else 0.0
            out[j] = min(1.0, max(0.0, out[j] + lacks / sj * (-1 if up else 1)))
            open_ = -1
            if not 0.0 < out[j] < 1.0:
                continue
        lacks, left = (1 - out[j]) * float(sizes[j]), out[j] * float(sizes[j])
        open_, up = j, draw.random() < out[j]
        if gives[j] < lacks if up else takes[j] < left:
            up = gives[j] >= lacks
    if open_ >= 0:
        out[open_] = float(out[open_] >= 0.5)
    return out


def held_back(sizes: np.ndarray, parts: np.ndarray) -> np.ndarray:
    """Of documents in falling order of size, the smallest open ones that together weigh HELD_WEIGHT times the largest."""
    at = np.flatnonzero((parts > 0) & (parts < 1))
    out = np.zeros(len(parts), dtype=bool)
    if len(at):
        up = at[::-1]
        out[up[: 1 + int(np.searchsorted(np.cumsum(sizes[up]), HELD_WEIGHT * sizes[at[0]]))]] = True
    return out


def _round_group(level: int, last: bool, seed: int):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["size", "doc_id", "row_key"], ascending=[False, True, True], kind="stable")
        first = rows.iloc[0]
        name = f"{seed}:{level}:{'' if first['source'] is None else 's' + str(first['source'])}:{first['bucket']}"
        draw = np.random.default_rng(zlib.crc32(name.encode()))
        sizes, parts = rows["size"].to_numpy(), rows["part"].to_numpy(dtype=float).copy()
        alone = (sizes == 0) & (parts > 0)
        parts[alone] = draw.random(int(alone.sum())) < parts[alone]
        held = held_back(sizes, parts)
        parts[~held] = settle(sizes[~held], parts[~held], draw)
        if last:
            parts = finish(sizes, parts, draw)
        done = (parts == 0) | (parts == 1)
        copies = pd.array(rows["base"].to_numpy() + np.where(done, parts, 0).astype("int64"), dtype="Int32")
        copies[~done] = pd.NA
        return rows.assign(part=parts, copies=copies)

    return run


def mix(docs: DataFrame, size: Column | None = None, row_key: Column | None = None, cap: float = 3.0, seed: int = 9) -> DataFrame:
    """One row per row of docs: doc_id, row_key, source, size, source_size, target, copies."""
    size = F.size(words(F.col("text"))) if size is None else size
    row_key = F.lit(0) if row_key is None else row_key
    sized = docs.select(F.col("doc_id").cast("long").alias("doc_id"), row_key.cast("long").alias("row_key"), F.col("source").cast("string").alias("source"), size.cast("long").alias("size"))
    sized = cut_lineage(sized)
    targets = cut_lineage(source_targets(sized, cap))
    few = targets.count() <= BROADCAST_SOURCES
    targets = targets.withColumnRenamed("source", "of")
    buckets = spread(sized.count(), LEAF_ROWS)
    rate = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(cap)))).otherwise(0.0)
    rows = sized.join(F.broadcast(targets) if few else targets, F.col("source").eqNullSafe(F.col("of"))).drop("of")
    rows = rows.select(
        "doc_id", "row_key", "source", "size", "source_size", "target", F.floor(rate).cast("int").alias("base"), (rate - F.floor(rate)).alias("part"),
        F.pmod(F.xxhash64("doc_id", "row_key"), F.lit(buckets)).cast("int").alias("bucket"), F.lit(None).cast("int").alias("copies"),
    )
    settled, level = [], 0
    while True:
        rows = cut_lineage(rows.groupBy("source", "bucket").applyInPandas(_round_group(level, buckets == 1, seed), _SCHEMA))
        settled.append(rows.filter("copies is not null"))
        if buckets == 1:
            break
        buckets, level = spread(buckets, FAN_IN), level + 1
        rows = rows.filter("copies is null").withColumn("bucket", (F.col("bucket") % buckets).cast("int"))
    out = settled[0]
    for more in settled[1:]:
        out = out.unionByName(more)
    return out.select("doc_id", "row_key", "source", "size", "source_size", "target", "copies")


def mix_documents(docs: DataFrame, seed: int = 9) -> DataFrame:
    """docs with each row as many times as the mix takes it. Equal rows share their copies."""
    columns = docs.columns
    keyed = docs.withColumn("mix_key", F.xxhash64(*[F.col(f"`{c}`") for c in columns]))
    copies = mix(keyed, row_key=F.col("mix_key"), seed=seed).groupBy("doc_id", "row_key").agg(F.sum("copies").alias("mix_copies")).filter("mix_copies > 0")
    copies = copies.select(F.col("doc_id").alias("mix_id"), F.col("row_key").alias("mix_row"), "mix_copies")
    one = keyed.dropDuplicates(["doc_id", "mix_key"])
    out = one.join(copies, (F.col("mix_key") == F.col("mix_row")) & F.col("doc_id").eqNullSafe(F.col("mix_id")))
    return out.withColumn("mix_nth", F.explode(F.sequence(F.lit(1), F.col("mix_copies")))).select(*[F.col(f"`{c}`") for c in columns])


def op9_mixing(spark, sf_dir: str) -> DataFrame:
    from .common import table

    docs = table(spark, sf_dir, "documents")
    return mix(docs).select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "source", "copies")
