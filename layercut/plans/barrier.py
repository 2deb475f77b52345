"""Exact emulation of the message-passing trainer: one barrier stage, a task a part, exchanges by allGather.

Payloads pass the driver, so that this is for small numbers of parts; it is the engine whose timers tell product, update and
communication apart.
"""

from __future__ import annotations

import json
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import BarrierTaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.activation import np_activate, np_prime
from ..operators.topology import Network


def train_barrier(net: Network, parts: DataFrame, p: int, vectors: list[tuple[dict, dict]], eta: float = 0.01, train: bool = True) -> DataFrame:
    """(part, kind, layer, row, col, value): new weights (kind weight), last outputs (kind output: layer = vector, row = neuron) and seconds
    by phase (kind product, update, comm). vectors: (inputs, targets) as {neuron: value}; parts hold the inputs' owners too."""
    rows = parts.select("layer", F.col("neuron").alias("row"), "part")
    links = net.weights.join(rows, ["layer", "row"]).select("part", "layer", "row", "col", "w")
    lists = parts.select("part", F.col("layer"), F.col("neuron").alias("row"), F.lit(None).cast("long").alias("col"), F.lit(None).cast("double").alias("w"))
    depth, kind = net.depth, net.activation
    owner = {(r["layer"], r["neuron"]): r["part"] for r in parts.collect()}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ctx = BarrierTaskContext.get()
        me = ctx.partitionId()
        mine = pd.concat(list(batches))
        spent = {"product": 0.0, "update": 0.0, "comm": 0.0}
        own, w = {}, {}
        for k in range(depth + 1):
            own[k] = np.sort(mine.loc[(mine["layer"] == k) & mine["col"].isna(), "row"].unique())
        for k in range(1, depth + 1):
            e = mine[(mine["layer"] == k) & mine["col"].notna()]
            need = np.sort(e["col"].unique()).astype(np.int64)
            w[k] = [np.searchsorted(own[k], e["row"].to_numpy()), np.searchsorted(need, e["col"].to_numpy().astype(np.int64)), e["w"].to_numpy().copy(), need]

        def exchange(by_part: dict[int, dict[int, float]]) -> list[dict[int, float]]:
            began = time.perf_counter()
            got = ctx.allGather(json.dumps({str(q): {str(n): v for n, v in m.items()} for q, m in by_part.items()}))
            out = [{int(n): v for n, v in json.loads(g).get(str(me), {}).items()} for g in got]
            spent["comm"] += time.perf_counter() - began
            return out

        # who needs my values: told once, since the pattern stays
        readers = {}
        for k in range(1, depth + 1):
            asked: dict[int, dict[int, float]] = {}
            for n in w[k][3].tolist():
                asked.setdefault(owner[(k - 1, n)], {})[n] = 0.0
            readers[k] = [sorted(m) for m in exchange(asked)]
        outputs = []
        for v, (given, wanted) in enumerate(vectors):
            xs, zs, seen = {0: {int(n): float(given.get(int(n), 0.0)) for n in own[0]}}, {}, {}
            for k in range(1, depth + 1):
                got = exchange({q: {n: xs[k - 1][n] for n in readers[k][q]} for q in range(p) if readers[k][q]})
                began = time.perf_counter()
                values = {n: x for m in got for n, x in m.items()}
                seen[k] = np.array([values[n] for n in w[k][3].tolist()])
                z = np.bincount(w[k][0], weights=w[k][2] * seen[k][w[k][1]], minlength=len(own[k])) if len(w[k][0]) else np.zeros(len(own[k]))
                zs[k] = z
                xs[k] = dict(zip(own[k].tolist(), np_activate(z, kind).tolist(), strict=True))
                spent["product"] += time.perf_counter() - began
            outputs += [(v, n, x) for n, x in xs[depth].items()]
            if not train:
                continue
            last = np.array(list(xs[depth].values()))
            delta = (last - np.array([wanted.get(n, 0.0) for n in own[depth].tolist()])) * np_prime(zs[depth], last, kind)
            for k in range(depth, 0, -1):
                began = time.perf_counter()
                s = np.bincount(w[k][1], weights=w[k][2] * delta[w[k][0]], minlength=len(w[k][3])) if len(w[k][0]) else np.zeros(0)
                spent["product"] += time.perf_counter() - began
                if k > 1:
                    back: dict[int, dict[int, float]] = {}
                    for n, x in zip(w[k][3].tolist(), s.tolist(), strict=True):
                        back.setdefault(owner[(k - 1, n)], {})[n] = x
                    got = exchange(back)
                began = time.perf_counter()
                if len(w[k][0]):
                    w[k][2] = w[k][2] - eta * delta[w[k][0]] * seen[k][w[k][1]]
                spent["update"] += time.perf_counter() - began
                if k > 1:
                    total = dict.fromkeys(own[k - 1].tolist(), 0.0)
                    for m in got:
                        for n, x in m.items():
                            total[n] += x
                    before = np.array(list(xs[k - 1].values()))
                    delta = np.array([total[n] for n in own[k - 1].tolist()]) * np_prime(zs[k - 1], before, kind)
        out = [(me, what, 0, 0, 0, s) for what, s in spent.items()] + [(me, "output", v, n, 0, x) for v, n, x in outputs]
        for k in range(1, depth + 1):
            out += [(me, "weight", k, int(own[k][r]), int(w[k][3][c]), float(x)) for r, c, x in zip(w[k][0], w[k][1], w[k][2], strict=True)]
        yield pd.DataFrame(out, columns=["part", "kind", "layer", "row", "col", "value"])

    placed = links.select("part", "layer", "row", "col", "w").unionByName(lists).repartitionById(p, F.col("part").cast("int"))
    return placed.mapInPandas(run, "part int, kind string, layer int, row long, col long, value double", barrier=True)


def breakdown(trained: DataFrame) -> DataFrame:
    """(kind, seconds, share): mean over the parts of time in products, updates and communication."""
    spent = trained.filter("kind in ('product', 'update', 'comm')").groupBy("kind").agg(F.avg("value").alias("seconds"))
    total = spent.agg(F.sum("seconds").alias("total"))
    return spent.crossJoin(total).select("kind", "seconds", F.try_divide("seconds", "total").alias("share"))  # one row
