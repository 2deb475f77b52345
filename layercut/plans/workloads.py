"""The published experiments on generated networks and the given tables; absolute times differ with the machine, counts don't."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import cut_aware, measures, partition, topology
from ..operators.encode import encode_images
from ..operators.routes import send_map
from ..operators.solver import graph_of, solve_chain
from ..session import cut_lineage
from ..sources.generators import strides
from ..sources.tables import read_table
from . import barrier, inference


def communication_table(spark: SparkSession, neurons=(256,), parts=(4, 8), layers: int = 6, degree: int = 16, seed: int = 42) -> DataFrame:
    """(neurons, p, scheme, avg_words, max_words, avg_msgs, max_msgs, balance, imbalance): random against cut-aware placement."""
    out = None
    for n in neurons:
        net = topology.radix_network(spark, n, layers, degree, seed=5)
        for p in parts:
            for scheme in ("random", "cut_aware"):
                rows = partition.random_parts(net.neurons, p, seed) if scheme == "random" else cut_aware.multilevel_parts(net, p, trials=1)
                full = cut_lineage(partition.with_inputs(net, rows, p))
                row = measures.cost_summary(measures.costs(spark, net.weights, full, send_map(net.weights, full), p))
                row = row.select(F.lit(n).alias("neurons"), F.lit(p).alias("p"), F.lit(scheme).alias("scheme"), "*")
                out = row if out is None else out.unionByName(row)
    return out


def random_row(neurons: int, degree: int, layers: int, p: int, seed: int = 0) -> dict[str, float]:
    """Words and messages sent a part (thousands, both passes, all layers) and imbalance for rows dealt at random: NumPy, structure only."""
    rng = np.random.default_rng(seed)
    steps, before = strides(neurons, degree), rng.integers(0, p, neurons)
    words, msgs, load = np.zeros(p), np.zeros(p), np.zeros(p)
    for k in range(layers):
        part = rng.integers(0, p, neurons)
        rows = np.repeat(np.arange(neurons), degree)
        cols = (rows + np.tile(np.arange(degree), neurons) * steps[k % len(steps)]) % neurons
        need = np.unique(cols * p + part[rows])
        src, dst = before[need // p], need % p
        away = src != dst
        words += np.bincount(src[away], minlength=p) + np.bincount(dst[away], minlength=p)
        pairs = np.unique(src[away] * p + dst[away])
        msgs += np.bincount(pairs // p, minlength=p) + np.bincount(pairs % p, minlength=p)
        load += np.bincount(part, minlength=p) * degree
        before = part
    return {"avg_words": words.mean() / 1e3, "max_words": words.max() / 1e3, "avg_msgs": msgs.mean() / 1e3, "max_msgs": msgs.max() / 1e3, "imbalance": load.max() / load.mean()}


def vector_times(spark: SparkSession, sf_dir: str, ps=(1, 2, 4), neurons: int = 64, layers: int = 4, degree: int = 8, vectors: int | None = None) -> DataFrame:
    """(scheme, p, vectors, ms, product, update, comm): mean time of a training step with the barrier engine, and of its parts, in ms."""
    net = topology.radix_network(spark, neurons, layers, degree)
    emb = read_table(spark, sf_dir, "embeddings")
    x = encode_images(emb if vectors is None else emb.orderBy("vec_id").limit(vectors)).toPandas()  # the sequence that one barrier stage trains on
    given = [({int(n): float(v) for n, v in zip(g["neuron"], g["x"], strict=True)}, {0: 1.0}) for _, g in x.groupby("vec_id")]
    rows = []
    for p in ps:
        for scheme in ("random", "cut_aware"):
            part = partition.random_parts(net.neurons, p) if scheme == "random" else cut_aware.multilevel_parts(net, p, trials=1)
            full = cut_lineage(partition.with_inputs(net, part, p))
            spent = {r["kind"]: 1000 * r["seconds"] / len(given) for r in barrier.breakdown(barrier.train_barrier(net, full, p, given)).collect()}
            rows.append((scheme, p, len(given), sum(spent.values()), spent["product"], spent["update"], spent["comm"]))
    return spark.createDataFrame(rows, "scheme string, p int, vectors int, ms double, product double, update double, comm double")


def inference_table(spark: SparkSession, sf_dir: str, sizes=((64, 4, 8), (256, 6, 16), (1024, 6, 32)), p: int = 4) -> DataFrame:
    """(neurons, layers, sharded, replicated, speedup): edges a second over all embeddings as one batch, the model on parts against replicas,
    and the first over the second. Placement and plans are made before the clock starts, as replicas are."""
    rows = []
    emb = read_table(spark, sf_dir, "embeddings")
    for n, layers, degree in sizes:
        net = topology.radix_network(spark, n, layers, degree)
        x = cut_lineage(encode_images(emb, int(n**0.5)))
        vectors = x.select("vec_id").distinct().count()
        full = cut_lineage(partition.with_inputs(net, cut_aware.multilevel_parts(net, p, trials=1), p))
        routes = cut_lineage(send_map(net.weights, full))
        edges = {}
        for engine, made in (("sharded", inference.infer_blocks(net, x, full, routes, p)), ("replicated", inference.infer_replicated(net, x))):
            began = time.perf_counter()
            made.write.format("noop").mode("overwrite").save()
            edges[engine] = measures.throughput(vectors, n * degree * layers, time.perf_counter() - began)
        rows.append((n, layers, edges["sharded"], edges["replicated"], edges["sharded"] / edges["replicated"]))
    return spark.createDataFrame(rows, "neurons int, layers int, sharded double, replicated double, speedup double")


def _radix_links(neurons: int, degree: int, layers: int) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    steps, links = strides(neurons, degree), {}
    for k in range(layers):
        rows = np.repeat(np.arange(neurons), degree)
        links[k + 1] = rows, (rows + np.tile(np.arange(degree), neurons) * steps[k % len(steps)]) % neurons
    return links


def partition_grid(spark: SparkSession, neurons=(256, 1024), ps=(4, 8, 16), layers=(2, 6), degree: int = 16, eps: float = 0.01) -> DataFrame:
    """(neurons, layers, p, seconds, cut, random_cut, ratio, placed, heaviest, capacity): one partitioning a row, each in a task of its own."""

    def one(combo: pd.DataFrame) -> pd.DataFrame:
        n, depth, p = (int(combo[c].iloc[0]) for c in ("neurons", "layers", "p"))
        links = _radix_links(n, degree, depth)
        began = time.perf_counter()
        made = solve_chain(links, p, eps, trials=1)
        seconds = time.perf_counter() - began
        rng, owner, base = np.random.default_rng(0), None, 0
        for k in sorted(links):
            g, ids = graph_of(*links[k], owner)
            part = rng.integers(0, p, len(ids))
            base += g.cut(part, p)
            owner = dict(zip(ids.tolist(), part.tolist(), strict=True))
        heaviest = max(int(np.bincount(part, minlength=p).max()) * degree for _, _, part, _, _ in made)
        whole = max(int(np.floor(np.round(n * degree / p * (1 + eps), 6))), -(-n // p) * degree)  # rows are not split
        cut = sum(m[3] for m in made)
        return pd.DataFrame([(n, depth, p, seconds, cut, base, cut / base, sum(len(m[1]) for m in made), heaviest, whole)], columns=names)

    names = ["neurons", "layers", "p", "seconds", "cut", "random_cut", "ratio", "placed", "heaviest", "capacity"]
    combos = spark.createDataFrame([(n, k, p) for n in neurons for k in layers for p in ps], "neurons int, layers int, p int")
    schema = "neurons int, layers int, p int, seconds double, cut long, random_cut long, ratio double, placed long, heaviest long, capacity long"
    each = len(neurons) * len(layers) * len(ps)
    return combos.repartition(each).mapInPandas(lambda batches: (one(b.iloc[i : i + 1]) for b in batches for i in range(len(b))), schema)


def step_table(spark: SparkSession, sf_dir: str, ps=(1, 2, 4), neurons: int = 64, layers: int = 4, degree: int = 8, vectors: int | None = None) -> DataFrame:
    """(scheme, p, vectors, ms, product, update, comm, speedup, efficiency, comm_gain): mean time of a training step with the barrier engine,
    its parts, speedup over random placement, efficiency against the fewest parts, and the share of the gain that communication has."""
    times = vector_times(spark, sf_dir, ps, neurons, layers, degree, vectors)
    rows = {(r["scheme"], r["p"]): r for r in times.collect()}  # a row a scheme and p
    out = []
    for (scheme, p), r in rows.items():
        base = rows[("random", p)]
        worth = measures.efficiency({q: rows[(scheme, q)]["ms"] for q in ps})[p]
        gain = base["ms"] - r["ms"]
        share = None if scheme == "random" or gain <= 0 else (base["comm"] - r["comm"]) / gain
        out.append((scheme, p, r["vectors"], r["ms"], r["product"], r["update"], r["comm"], base["ms"] / r["ms"], worth, share))
    return spark.createDataFrame(out, "scheme string, p int, vectors int, ms double, product double, update double, comm double, speedup double, efficiency double, comm_gain double")
