"""Operator 8 [native]: quality rules under weak supervision.

Each rule looks at a document's counts and votes good, bad or nothing. Expectation-maximisation over the counts of vote patterns
(3 to the number of rules at most, whatever the corpus) estimates how often each rule is right and how many documents are good;
the posterior probability that a document is good then replaces a demand that all rules pass. All work on documents is DataFrame
expressions inside one row: nothing is exploded or shuffled but the vote patterns.

Repeated 3-word windows are found by sorting a row's window hashes with their positions; two different windows of one document
share a 64-bit hash with a chance below 1e-8 even in a document of half a million words.

Defined results: null and empty texts have no words and fail the base rule; repeated rows are judged alike; an empty table gives an
empty result; a document on which every rule abstains gets the prior.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut_lineage, squash_white, table, words

# The characters counted as symbols.
SYMBOLS = "#*$%&|<>"
ROUNDS, KEEP_FROM = 40, 0.5


def counts(docs: DataFrame) -> DataFrame:
    """docs (with text) and n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    df = docs.withColumn("q_text", F.coalesce(F.col("text").cast("string"), F.lit("")))
    df = df.withColumn("q_words", words(F.col("q_text")))
    n = F.size("q_words")
    bare = F.replace(squash_white(F.col("q_text")), F.lit(" "), F.lit(""))
    kept = bare
    for c in SYMBOLS:
        kept = F.replace(kept, F.lit(c), F.lit(""))
    df = df.withColumn("word_chars", F.length(bare).cast("long")).withColumn("n_symbols", (F.length(bare) - F.length(kept)).cast("long"))
    df = df.withColumn("q_lines", F.filter(F.split("q_text", "\n", -1), lambda x: F.length(F.replace(squash_white(x), F.lit(" "), F.lit(""))) > 0))
    df = df.withColumn("n_dup_lines", (F.size("q_lines") - F.size(F.array_distinct("q_lines"))).cast("long"))
    triples = F.arrays_zip(
        F.slice("q_words", 1, F.greatest(n - 2, F.lit(0))).alias("a"), F.slice("q_words", 2, F.greatest(n - 2, F.lit(0))).alias("b"), F.slice("q_words", 3, F.greatest(n - 2, F.lit(0))).alias("c")
    )
    df = df.withColumn("q_triples", F.when(n >= 3, triples))
    df = df.withColumn("q_windows", F.sort_array(F.transform("q_triples", lambda t, i: F.struct(F.xxhash64(t["a"], t["b"], t["c"]).alias("h"), i.alias("i")))))
    at = F.col("q_windows")
    again = F.filter(at, lambda w, k: F.coalesce(F.get(at, k - 1)["h"] == w["h"], F.lit(False)) | F.coalesce(F.get(at, k + 1)["h"] == w["h"], F.lit(False)))
    df = df.withColumn("q_again", F.sort_array(F.transform(again, lambda w: w["i"])))
    seen = F.col("q_again")
    covered = F.aggregate(F.transform(seen, lambda p, k: F.least(F.lit(3), F.coalesce(p - F.get(seen, k - 1), F.lit(3)))), F.lit(0).cast("long"), lambda a, x: a + x)
    df = df.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long")).withColumn("n_words", n.cast("long"))
    return df.drop("q_text", "q_words", "q_lines", "q_triples", "q_windows", "q_again")


def rules() -> dict[str, tuple[Column, Column]]:
    """Name -> (when it votes good, when it votes bad); otherwise it abstains."""
    n = F.col("n_words")
    return {
        "length": (n >= 100, n < 50),
        "symbols": (F.col("n_symbols") * 100 <= n, F.col("n_symbols") * 10 > n),
        "lines": (F.col("n_dup_lines") == 0, F.col("n_dup_lines") >= 4),
        "repeats": (F.col("n_repeat_words") * 100 <= 10 * n, F.col("n_repeat_words") * 100 > 30 * n),
        "word_length": ((F.col("word_chars") >= 3 * n) & (F.col("word_chars") <= 10 * n), (F.col("word_chars") < 2 * n) | (F.col("word_chars") > 14 * n)),
        "substance": (F.col("word_chars") >= 500, F.col("word_chars") < 150),
    }


def vote(good: Column, bad: Column) -> Column:
    return F.when(bad, -1).when(good, 1).otherwise(0)


def estimate(patterns: list[tuple[tuple[int, ...], int]], rounds: int = ROUNDS) -> tuple[float, list[float]]:
    """(prior of good, accuracy of each rule) from (votes, documents)."""
    width = len(patterns[0][0]) if patterns else 0
    prior, right = 0.7, [0.75] * width
    for _ in range(rounds):
        good = total = 0.0
        hit, voted = [1.5] * width, [2.0] * width  # a weak belief in the rules keeps the two classes named
        for votes, n in patterns:
            p = posterior(votes, prior, right)
            good, total = good + n * p, total + n
            for j, v in enumerate(votes):
                if v:
                    hit[j], voted[j] = hit[j] + n * (p if v > 0 else 1 - p), voted[j] + n
        prior = min(0.99, max(0.01, good / total)) if total else prior
        right = [min(0.99, max(0.5, h / v)) for h, v in zip(hit, voted, strict=True)]
    return prior, right


def posterior(votes: tuple[int, ...], prior: float, right: list[float]) -> float:
    at = math.log(prior / (1 - prior)) + sum(v * math.log(r / (1 - r)) for v, r in zip(votes, right, strict=True))
    return 1 / (1 + math.exp(-at))


def judge(docs: DataFrame, keep_from: float = KEEP_FROM) -> DataFrame:
    """docs without text, with the counts, base_failed, quality (the posterior) and kept."""
    made = rules()
    df = counts(docs).drop("text").withColumns({f"vote_{k}": vote(*v) for k, v in made.items()})
    df = cut_lineage(df)
    names = [f"vote_{k}" for k in made]
    tally = [(tuple(r[k] for k in names), r["n"]) for r in df.groupBy(*names).agg(F.count(F.lit(1)).alias("n")).collect()]  # 3 ** rules at most
    prior, right = estimate(sorted(tally) or [((0,) * len(names), 0)])
    at = F.lit(math.log(prior / (1 - prior)))
    for name, r in zip(names, right, strict=True):
        at = at + F.col(name) * F.lit(math.log(r / (1 - r)))
    df = df.withColumn("quality", 1 / (1 + F.exp(-at))).drop(*names)
    df = df.withColumn("base_failed", (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")))
    return df.withColumn("kept", ~F.col("base_failed") & (F.col("quality") >= keep_from))


def op8_quality(spark, sf_dir: str) -> DataFrame:
    out = judge(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "quality")
