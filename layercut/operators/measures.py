"""Cost and accuracy measures over routes, parts and weights."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .routes import message_sizes


def volume_by_layer(routes: DataFrame, passes: int = 2) -> DataFrame:
    """(layer, words): passes = 2 counts forward and backward, which are equal."""
    return routes.groupBy("layer").agg((F.count_if(F.col("src") != F.col("dst")) * passes).alias("words"))


def connectivity(weights: DataFrame, parts: DataFrame, pinned: bool = True) -> DataFrame:
    """(layer, net, lam): parts that a column's rows (and, pinned, its input's owner) touch; a net is a column with links."""
    rows = parts.select("layer", F.col("neuron").alias("row"), "part")
    pins = weights.join(rows, ["layer", "row"]).select("layer", F.col("col").alias("net"), "part")
    if pinned:
        nets = pins.select("layer", "net").distinct()
        owner = parts.select((F.col("layer") + 1).alias("layer"), F.col("neuron").alias("net"), "part")
        pins = pins.unionByName(nets.join(owner, ["layer", "net"]).select("layer", "net", "part"))
    return pins.groupBy("layer", "net").agg(F.count_distinct("part").cast("int").alias("lam"))


def connectivity_mask(weights: DataFrame, parts: DataFrame) -> DataFrame:
    """connectivity() without the owner, for 63 parts at most: the set as bits of one BIGINT, no distinct."""
    rows = parts.select("layer", F.col("neuron").alias("row"), "part")
    bit = F.expr("shiftleft(CAST(1 AS BIGINT), part)")
    return weights.join(rows, ["layer", "row"]).groupBy("layer", F.col("col").alias("net")).agg(F.bit_count(F.bit_or(bit)).alias("lam"))


def connectivity_sketch(weights: DataFrame, parts: DataFrame) -> DataFrame:
    """(layer, sketch) of distinct (net, part) pairs, to be merged over runs by hll_union_agg."""
    rows = parts.select("layer", F.col("neuron").alias("row"), "part")
    pairs = weights.join(rows, ["layer", "row"]).select("layer", F.concat_ws(":", "col", "part").alias("pair"))
    return pairs.groupBy("layer").agg(F.hll_sketch_agg("pair").alias("sketch"))


def cut_size(weights: DataFrame, parts: DataFrame, cost: int = 2, pinned: bool = True) -> DataFrame:
    """(layer, cut_nets, cut): cost * (lam - 1) over the nets. With pinned owners and cost 2 it is the layer's volume."""
    lam = connectivity(weights, parts, pinned)
    return lam.groupBy("layer").agg(F.count_if(F.col("lam") > 1).alias("cut_nets"), (F.sum(F.col("lam") - 1) * cost).cast("bigint").alias("cut"))


def lambda_histogram(weights: DataFrame, parts: DataFrame) -> DataFrame:
    return connectivity(weights, parts).groupBy("layer", "lam").agg(F.count(F.lit(1)).alias("nets"))


def loads(weights: DataFrame, parts: DataFrame, share_count: int) -> DataFrame:
    """(layer, part, load): links of the rows of each part, parts without any included."""
    rows = parts.select("layer", F.col("neuron").alias("row"), "part")
    have = weights.join(rows, ["layer", "row"]).groupBy("layer", "part").agg(F.count(F.lit(1)).alias("load"))
    every = weights.select("layer").distinct().crossJoin(weights.sparkSession.range(share_count).select(F.col("id").cast("int").alias("part")))  # layers x parts
    return every.join(have, ["layer", "part"], "left").select("layer", "part", F.coalesce("load", F.lit(0)).cast("bigint").alias("load"))


def imbalance_by_layer(weights: DataFrame, parts: DataFrame, p: int) -> DataFrame:
    return loads(weights, parts, p).groupBy("layer").agg((F.max("load") / F.avg("load")).alias("imbalance"))


def imbalance(weights: DataFrame, parts: DataFrame, p: int, scope: str = "network") -> DataFrame:
    """One row. network: loads summed over the layers first; layer_max, layer_mean: over the layers' own."""
    if scope == "network":
        total = loads(weights, parts, p).groupBy("part").agg(F.sum("load").alias("load"))
        return total.agg((F.max("load") / F.avg("load")).alias("imbalance"))
    fold = {"layer_max": F.max, "layer_mean": F.avg}[scope]
    return imbalance_by_layer(weights, parts, p).agg(fold("imbalance").alias("imbalance"))


def costs(spark: SparkSession, weights: DataFrame, parts: DataFrame, routes: DataFrame, p: int) -> DataFrame:
    """(part, sent_words, sent_msgs, recv_words, recv_msgs, load) over all layers and both passes, for all p parts."""
    m = message_sizes(routes)
    sent = m.groupBy(F.col("src").alias("part")).agg(F.sum("words").alias("sent_words"), F.count(F.lit(1)).alias("sent_msgs"))
    got = m.groupBy(F.col("dst").alias("part")).agg(F.sum("words").alias("recv_words"), F.count(F.lit(1)).alias("recv_msgs"))
    load = loads(weights, parts, p).groupBy("part").agg(F.sum("load").alias("load"))
    every = spark.range(p).select(F.col("id").cast("int").alias("part"))
    out = every.join(sent, "part", "left").join(got, "part", "left").join(load, "part", "left")
    return out.select("part", *[F.coalesce(c, F.lit(0)).cast("bigint").alias(c) for c in ("sent_words", "sent_msgs", "recv_words", "recv_msgs", "load")])


def cost_summary(per_part: DataFrame) -> DataFrame:
    """One row: average and maximum of words and messages sent, communication balance, computational imbalance."""
    return per_part.agg(
        F.avg("sent_words").alias("avg_words"), F.max("sent_words").alias("max_words"), F.avg("sent_msgs").alias("avg_msgs"), F.max("sent_msgs").alias("max_msgs"),
        F.try_divide(F.max("sent_words"), F.avg("sent_words")).alias("balance"), F.try_divide(F.max("load"), F.avg("load")).alias("imbalance"),
    )


def ratio_report(cut_aware: DataFrame, random: DataFrame) -> DataFrame:
    """cost_summary() of two partitions as ratios and percent saved."""
    a, b = cut_aware.select([F.col(c).alias(f"a_{c}") for c in cut_aware.columns]), random.select([F.col(c).alias(f"b_{c}") for c in random.columns])
    both = a.crossJoin(b)  # one row each
    names = ["avg_words", "max_words", "avg_msgs", "max_msgs"]
    return both.select(*[F.try_divide(F.col(f"a_{n}"), F.col(f"b_{n}")).alias(f"{n}_ratio") for n in names], *[(100 * (1 - F.try_divide(F.col(f"a_{n}"), F.col(f"b_{n}")))).alias(f"{n}_saved") for n in names])


def internode_volume(routes: DataFrame, cores: int) -> DataFrame:
    """Words by layer that cross nodes of so many parts each: one copy for each node in need."""
    nodes = routes.select("layer", "neuron", F.floor(F.col("src") / cores).cast("int").alias("src"), F.floor(F.col("dst") / cores).cast("int").alias("dst")).distinct()
    return volume_by_layer(nodes)


def dynamic_volume(routes: DataFrame, values: DataFrame) -> DataFrame:
    """Forward words by layer if zeros were not sent. values (layer, vec_id, neuron, x): x^(layer - 1)."""
    sent = routes.filter("src <> dst").join(values.filter("x <> 0"), ["layer", "neuron"])
    return sent.groupBy("layer").agg(F.count(F.lit(1)).alias("words"))


def locality(weights: DataFrame, parts: DataFrame) -> DataFrame:
    """(layer, inputs): distinct inputs that parts read, summed over the parts; fewer means better reuse."""
    rows = parts.select("layer", F.col("neuron").alias("row"), "part")
    return weights.join(rows, ["layer", "row"]).select("layer", "part", "col").distinct().groupBy("layer").agg(F.count(F.lit(1)).alias("inputs"))


def memory_share(weights: DataFrame, parts: DataFrame, bytes_per_link: int = 20) -> DataFrame:
    """(part, model_bytes, share): what a part stores; a replica stores the sum."""
    rows = parts.select("layer", F.col("neuron").alias("row"), "part")
    per = weights.join(rows, ["layer", "row"]).groupBy("part").agg((F.count(F.lit(1)) * bytes_per_link).alias("model_bytes"))
    return per.withColumn("share", F.col("model_bytes") / F.sum("model_bytes").over(Window.partitionBy(F.lit(1))))


def expected_random_volume(neurons: int, degree: int, layers: int, p: int) -> float:
    """Words a part sends, both passes and all layers, for rows dealt at random with that many inputs each."""
    return neurons * (p - 1) * (1 - (1 - 1 / p) ** degree) * 2 * layers / p


def expected_random_words(weights: DataFrame, ps: list[int]) -> DataFrame:
    """(parts, words): expected_random_volume() of a given network, whose inputs have readers of any number. Inputs are counted by that number
    first, so that few terms are added."""
    readers = weights.groupBy("layer", "col").agg(F.count(F.lit(1)).alias("d")).groupBy("d").agg(F.count(F.lit(1)).alias("n"))
    p = F.col("parts").cast("double")
    words = F.col("n") * (p - 1) * (1 - F.pow(1 - 1 / p, F.col("d").cast("double"))) * 2 / p
    return readers.select("n", "d", F.explode(F.array(*[F.lit(q) for q in ps])).alias("parts")).groupBy("parts").agg(F.sum(words).alias("words"))


def hypergraph_size(weights: DataFrame) -> DataFrame:
    """(layer, vertices, nets, pins): pins hold one fixed pin a net."""
    return weights.groupBy("layer").agg(F.count_distinct("row").alias("vertices"), F.count_distinct("col").alias("nets"), (F.count(F.lit(1)) + F.count_distinct("col")).alias("pins"))


def throughput(vectors: int, links: int, seconds: float) -> float:
    """Edges a second: vectors times connections over time."""
    return vectors * links / seconds


def break_even(partition_seconds: float, seconds_saved: float) -> float:
    """Vectors after which partitioning has paid."""
    return float("inf") if seconds_saved <= 0 else partition_seconds / seconds_saved


def break_even_column(cost: Column, saved: Column) -> Column:
    """break_even() of counted costs."""
    return F.when(saved > 0, cost / saved).otherwise(F.lit(float("inf")))


def ideal_times(first, first_p: int, ps: list[int]) -> list:
    """A number or a column for each of ps."""
    return [first * first_p / p for p in ps]


def efficiency(times: dict[int, float]) -> dict[int, float]:
    p0 = min(times)
    return {p: times[p0] * p0 / (t * p) for p, t in times.items()}


def confusion(predicted: DataFrame, labels: DataFrame) -> DataFrame:
    """(label, predicted, n)."""
    return predicted.join(labels, "vec_id").groupBy("label", "predicted").agg(F.count(F.lit(1)).alias("n"))


def exchanges(df: DataFrame) -> int:
    """Shuffle exchanges of the executed plan; cached and checkpointed inputs are leaves."""
    df = df
    todo, seen = [df._jdf.queryExecution().executedPlan()], 0
    while todo:
        node = todo.pop()
        name = node.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            todo.append(node.initialPlan())
            continue
        seen += name == "ShuffleExchangeExec"
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
    return seen
