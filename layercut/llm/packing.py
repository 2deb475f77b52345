"""Operator 10: best-fit packing by minimum bin slack.

Texts become ids (the vocabulary of byte_bpe_50k.json; ids equal those of the tokenizers library) plus an end id. Longer documents
are cut into full pieces behind a first piece that takes the remainder, so each document leaves one partly filled piece at most.
Bins are planned on the counts of piece lengths, at most 1,024 numbers whatever the corpus: per bin the longest piece left is
placed, a bitset subset-sum over the lengths still available finds the fullest completion, and the combination found is used as
often as its lengths allow before they are removed. Pieces then find their places by their rank within their length.

Defined results: null and empty texts are the end id alone; repeated rows are packed as documents of their own; an empty table
gives an empty result; no piece is dropped or shortened.
"""

from __future__ import annotations

import base64
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut_lineage, spread, table

#: Capacity and the id that ends a document.
CAPACITY, END_ID = 1024, 2
#: Rows of a (length, bucket) group when pieces are ranked; buckets of a stretch, whose counts one task adds up.
RANK_ROWS, STRETCH = 512, 1 << 14
_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


class Encoder:
    """Ids of whole texts, as Tokenizer.encode(text, add_special_tokens=False) of the tokenizers library gives them.

    The rank file of the same vocabulary encodes about five times as fast; texts that hold a special token's string go to the
    tokenizers library itself.
    """

    def __init__(self, tokenizer_file: str, rank_file: str, pattern: str):
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(rank_file, "rb"))}
        self.fast = tiktoken.Encoding("packing", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.file, self.full = tokenizer_file, None

    def __call__(self, text: str) -> list[int]:
        if "<|endoftext|>" in text:
            if self.full is None:
                from tokenizers import Tokenizer

                self.full = Tokenizer.from_file(self.file)
            return self.full.encode(text, add_special_tokens=False).ids
        return self.fast.encode_ordinary(text)


def default_encoder() -> Encoder:
    import public_tokenizers

    return Encoder(public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def pieces(docs: DataFrame, make_encoder=default_encoder, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every document, whole."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        encode = make_encoder()
        for batch in batches:
            rows, last, ids = [], None, np.empty(0, "<u4")
            for doc_id, text in zip(batch["doc_id"], batch["text"], strict=True):
                text = text if isinstance(text, str) else ""
                if text != last:
                    last, ids = text, np.array([*encode(text), end_id], dtype="<u4")
                head = len(ids) % capacity or capacity
                for k, (a, b) in enumerate(zip([0, *range(head, len(ids), capacity)], range(head, len(ids) + 1, capacity), strict=True)):
                    rows.append((doc_id, k, a, b - a, zlib.crc32(ids[a:b].tobytes())))
            out = pd.DataFrame(rows, columns=["doc_id", "piece", "start", "length", "ids_crc32"])
            out["doc_id"] = out["doc_id"].astype("Int64")
            yield out

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInPandas(run, _PIECES)


def fullest(slack: int, available: dict[int, int]) -> dict[int, int]:
    """Lengths and how many of each: a feasible combination that leaves the least of slack unused."""
    reach, steps = 1, []
    for length in sorted(available, reverse=True):
        left, take = min(available[length], slack // length), 1
        while left > 0 and not reach >> slack & 1:
            take = min(take, left)
            steps.append((length, take, reach))
            reach |= (reach << length * take) & ((1 << slack + 1) - 1)
            left, take = left - take, take * 2
        if reach >> slack & 1:
            break
    at, used = reach.bit_length() - 1, {}
    for length, take, before in reversed(steps):
        if not before >> at & 1:
            used[length] = used.get(length, 0) + take
            at -= length * take
    return used


def plan_bins(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, end rank, first sequence, pieces a sequence, offset of the first) for ranks within each length."""
    left, given = {k: v for k, v in counts.items() if v}, dict.fromkeys(counts, 0)
    out, sequence = [], 0
    while left:
        longest = max(left)
        rest = left | {longest: left[longest] - 1}
        combo = fullest(capacity - longest, {k: v for k, v in rest.items() if v and k <= capacity - longest})
        combo[longest] = combo.get(longest, 0) + 1
        times = min(left[k] // n for k, n in combo.items())
        offset = 0
        for k, n in sorted(combo.items(), reverse=True):
            out.append((k, given[k], given[k] + n * times, sequence, n, offset))
            offset += k * n
            given[k] += n * times
            left[k] -= n * times
            if not left[k]:
                del left[k]
        sequence += times
    return out


def pack(cut: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """cut (of pieces()) with sequence_id and offset. cut is read twice: hand in a checkpoint or a table."""
    spark = cut.sparkSession
    counts = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # capacity rows at most
    buckets = spread(sum(counts.values()), RANK_ROWS)
    bins = spark.createDataFrame(plan_bins(counts, capacity) or [(0, 0, 0, 0, 1, 0)], "of long, first long, past long, sequence0 long, each long, offset0 long")
    keyed = cut.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(buckets)).cast("int"))
    before = keyed.groupBy("length", "bucket").agg(F.count(F.lit(1)).alias("n")).withColumn("stretch", F.floor(F.col("bucket") / STRETCH))
    inside = F.sum("n").over(Window.partitionBy("length", "stretch").orderBy("bucket")) - F.col("n")
    whole = before.groupBy("length", "stretch").agg(F.sum("n").alias("all"))
    whole = whole.withColumn("ahead", F.sum("all").over(Window.partitionBy("length").orderBy("stretch")) - F.col("all"))  # a row per 8 million pieces
    before = before.withColumn("inside", inside).join(whole, ["length", "stretch"]).select("length", "bucket", (F.col("ahead") + F.col("inside")).alias("ahead"))
    ranked = keyed.withColumn("nth", F.row_number().over(Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "ids_crc32")))
    ranked = ranked.join(before, ["length", "bucket"]).withColumn("rank", F.col("ahead") + F.col("nth") - 1)
    placed = ranked.join(F.broadcast(bins), (F.col("length") == F.col("of")) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("past")))  # a few thousand rows
    at = F.col("rank") - F.col("first")
    return placed.select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        (F.col("sequence0") + F.floor(at / F.col("each"))).cast("long").alias("sequence_id"), (F.col("offset0") + at % F.col("each") * F.col("length")).cast("long").alias("offset"),
    )


def pack_documents(docs: DataFrame, make_encoder=default_encoder, capacity: int = CAPACITY) -> DataFrame:
    return pack(cut_lineage(pieces(docs, make_encoder, capacity)), capacity)


def op10_packing(spark, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
