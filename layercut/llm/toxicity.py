"""Operator 3: toxicity by class-conditional Kneser-Ney models.

One model for toxic and one for ordinary text, each learned from a bounded sample of labelled documents. A word's probability is
discounted absolutely and backs off to its stem (its first letters), whose probability comes from continuation counts: how many
different words of the class begin so. Stems back off to shared continuation counts over all documents, labelled or not, exact by
stem in a table that grows with the vocabulary: the models take the counts of their own stems from it, and its totals. Rare
expressions unseen in both classes thus get the same probability twice. Below the word the
spelling given the stem is the same in both models. A document's log-likelihood ratio is normalised by length, over the whole
text and over its windows of a few words; a logistic curve, fitted on labelled documents that neither model has seen, maps these
to a score. A word counts once a document. The word before as a further level was measured and left out (README).

Defined results: null, empty and word-less texts have the ratios 0; repeated rows are scored alike; labels that contradict each
other count as toxic; with one class or none labelled every score is 0; an empty table gives an empty result. Labels, lang, source
and doc_id are no inputs of a score.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut_lineage, table, words

#: Bound of the sample: so many documents of either class teach the models and the curve.
SAMPLE_DOCS = 3000
#: Letters of a stem; words of the windows; what counts of 1, and of more, give to the backoff.
STEM, WINDOWS, DISCOUNTS = 4, (1, 6), (1.0, 1.5)
THRESHOLD = 0.3
_WORD = re.compile(r"[^\W_]+")


def word_column(text):
    """Words as the scorer finds them: runs of letters and digits of the lower-cased text."""
    return words(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def remainder(doc_id):
    return F.crc32(doc_id.cast("string").cast("binary")) % 4


@dataclass
class Shared:
    """Different words of the corpus by stem, for the stems that the models hold; total: all its words and stems, and one stem for the rest."""

    counts: dict[str, int]
    total: float

    def of(self, stem: str) -> float:
        return self.counts.get(stem, 0) + 1


def stem_table(docs: DataFrame) -> DataFrame:
    """(stem, n): how many different words of all documents begin so."""
    seen = docs.select(F.explode(word_column(F.col("text").cast("string"))).alias("word")).distinct()
    return cut_lineage(seen.groupBy(F.substring("word", 1, STEM).alias("stem")).agg(F.count(F.lit(1)).alias("n")))


def shared_counts(docs: DataFrame, counts: DataFrame) -> Shared:
    """Exact counts for the stems of counts (word), which the sample bounds, and the exact total over all stems."""
    stems = stem_table(docs)
    total = stems.agg(F.sum("n").alias("words"), F.count(F.lit(1)).alias("stems")).first()
    wanted = counts.select(F.substring("word", 1, STEM).alias("stem")).distinct()
    found = stems.join(wanted, "stem").toArrow()
    return Shared(dict(zip(found["stem"].to_pylist(), found["n"].to_pylist(), strict=True)), float((total["words"] or 0) + total["stems"] + 1))


def off(n: int, discounts: tuple[float, float] = DISCOUNTS) -> float:
    """What a count gives to the backoff."""
    return min(n, discounts[n > 1])


class ClassModel:
    """Kneser-Ney probabilities of one class. counts: in how many documents a word stands; shared: corpus counts by stem."""

    def __init__(self, counts: dict[str, int], shared: Shared):
        self.counts, self.shared = counts, shared
        self.mass = float(sum(counts.values()))
        self.stems: dict[str, int] = {}
        for word in counts:
            self.stems[word[:STEM]] = self.stems.get(word[:STEM], 0) + 1
        self.back = sum(map(off, counts.values())) / self.mass
        self.stem_back = sum(map(off, self.stems.values())) / len(counts)

    def stem(self, stem: str) -> float:
        n = self.stems.get(stem, 0)
        return (n - off(n)) / len(self.counts) + self.stem_back * self.shared.of(stem) / self.shared.total

    def word(self, word: str) -> float:
        """The spelling given the stem is one over the corpus' words of the stem and one for all others."""
        n, stem = self.counts.get(word, 0), word[:STEM]
        return (n - off(n)) / self.mass + self.back * self.stem(stem) / self.shared.of(stem)


@dataclass
class Ratios(dict):
    """Word -> log(toxic / ordinary). Words of neither class fall back to their stem, unseen stems to a constant."""

    stems: dict[str, float] = field(default_factory=dict)
    unseen: float = 0.0

    def __missing__(self, word: str) -> float:
        return self.stems.get(word[:STEM], self.unseen)


def learn(toxic: ClassModel, ordinary: ClassModel) -> Ratios:
    ratio = lambda a, b: float(np.log(a) - np.log(b))
    out = Ratios()
    for stem in {*toxic.stems, *ordinary.stems}:  # of words that neither class holds: their spelling is the same in both
        out.stems[stem] = ratio(toxic.back * toxic.stem(stem), ordinary.back * ordinary.stem(stem))
    for word in {*toxic.counts, *ordinary.counts}:
        out[word] = ratio(toxic.word(word), ordinary.word(word))
    out.unseen = ratio(toxic.back * toxic.stem_back, ordinary.back * ordinary.stem_back)
    return out


def ratios_of(text: str | None, model: Ratios, windows: tuple[int, ...] = WINDOWS) -> tuple[float, ...]:
    """Mean log-ratio of the text, and the largest mean of its windows of each length."""
    found = _WORD.findall((text or "").lower())
    if not found:
        return (0.0,) * (1 + len(windows))
    sums = np.concatenate([[0.0], np.cumsum(np.fromiter(map(model.__getitem__, found), dtype=float, count=len(found)))])
    tops = [(sums[k:] - sums[:-k]).max() / w for w in windows for k in [min(w, len(found))]]
    return float(sums[-1] / len(found)), *map(float, tops)


def fit_curve(x: np.ndarray, y: np.ndarray, prior: float, rounds: int = 50, ridge: float = 1e-5) -> np.ndarray:
    """Logistic regression by Newton's method; toxic rows weigh prior in all, whatever their share of the sample."""
    design = np.column_stack([np.ones(len(x)), x])
    weight = np.where(y == 1, prior / max(1, (y == 1).sum()), (1 - prior) / max(1, (y == 0).sum())) * len(y)
    b = np.zeros(design.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(design @ b, -30, 30)))
        h = (design * (weight * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ design + ridge * len(y) * np.eye(len(b))
        step = np.linalg.solve(h, design.T @ (weight * (y - p)) - ridge * len(y) * b)
        b += step
        if np.abs(step).max() < 1e-8:
            break
    return b


@dataclass
class Scorer:
    model: Ratios
    curve: np.ndarray | None

    def score(self, text: str | None) -> float:
        if self.curve is None:
            return 0.0
        at = self.curve[0] + self.curve[1:] @ np.array(ratios_of(text, self.model))
        return float(1 / (1 + np.exp(-np.clip(at, -30, 30))))


def train(docs: DataFrame, labels: DataFrame, sample_docs: int = SAMPLE_DOCS) -> Scorer:
    """Learns from labelled rows whose remainder is not 2: 0 and 1 for the models, 3 for the curve."""
    known = labels.filter("toxic in (0, 1) and doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), "toxic")
    known = known.filter(remainder(F.col("doc_id")) != 2).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    known = cut_lineage(known)
    prior = known.agg(F.avg("toxic")).first()[0]
    taken = [known.filter(F.col("toxic") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs) for c in (0, 1)]
    sample = cut_lineage(taken[0].unionByName(taken[1]))  # 2 * sample_docs rows at most
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    texts = cut_lineage(texts.join(F.broadcast(sample), "doc_id").withColumn("curve", remainder(F.col("doc_id")) == 3))
    counts = cut_lineage(texts.filter("not curve").select("toxic", F.explode(F.array_distinct(word_column(F.col("text")))).alias("word")).groupBy("toxic", "word").agg(F.count(F.lit(1)).alias("n")))
    split: list[dict[str, int]] = [{}, {}]
    for toxic, word, n in zip(*(c.to_pylist() for c in counts.toArrow().columns), strict=True):
        split[toxic][word] = n
    if not split[0] or not split[1]:
        return Scorer(Ratios(), None)
    shared = shared_counts(docs, counts)
    model = learn(ClassModel(split[1], shared), ClassModel(split[0], shared))
    shipped = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the sample

    def measure(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            at = np.array([ratios_of(t, shipped.value) for t in batch["text"]]).reshape(len(batch), 1 + len(WINDOWS))
            yield pd.DataFrame(at, columns=names).assign(toxic=batch["toxic"].to_numpy())[["toxic", *names]]

    names = ["mean", *(f"top{w}" for w in WINDOWS)]
    fit = texts.filter("curve").select("toxic", "text").mapInPandas(measure, ", ".join(["toxic int", *(f"{n} double" for n in names)])).toPandas()
    if fit["toxic"].nunique() < 2:
        return Scorer(model, np.array([0.0, *[1.0] * len(names)]))
    return Scorer(model, fit_curve(fit[names].to_numpy(), fit["toxic"].to_numpy(), prior))


def score_documents(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """docs with tox_score, from the whole text of each row."""
    shipped = docs.sparkSession.sparkContext.broadcast(scorer)

    @F.pandas_udf("double")
    def score(texts: pd.Series) -> pd.Series:
        return pd.Series([shipped.value.score(t) for t in texts], dtype=float)

    return docs.withColumn("tox_score", score(F.col("text").cast("string")))


def op3_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    out = score_documents(docs, train(docs, table(spark, sf_dir, "labels")))
    return out.select("doc_id", (remainder(F.col("doc_id")) == 2).alias("held_out"), F.col("tox_score").alias("score"), (F.col("tox_score") >= THRESHOLD).cast("int").alias("predicted"))


def drop_toxic(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score stays below the threshold, with their own columns only."""
    scorer = train(docs, table(spark, sf_dir, "labels"))
    return score_documents(docs, scorer).filter(F.col("tox_score") < THRESHOLD).select(*[F.col(f"`{c}`") for c in docs.columns])
