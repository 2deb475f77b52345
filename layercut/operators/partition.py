"""Partitions that don't look at the cut, capacities, owners of inputs, and the hypergraph of a layer as views."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import portable_hash
from .topology import Network


def random_parts(neurons: DataFrame, p: int, seed: int = 42, balanced: bool = False) -> DataFrame:
    """Rows dealt by hash: independent draws, or (balanced) dealt in turn after a shuffle by hash. Layer 0 is left out: see assign_inputs."""
    rows = neurons.filter("layer > 0")
    h = portable_hash(F.col("layer"), F.col("neuron"), seed)
    if not balanced:
        return rows.select("layer", "neuron", (h % p).cast("int").alias("part"))
    nth = F.row_number().over(Window.partitionBy("layer").orderBy(h, "neuron")) - 1
    return rows.select("layer", "neuron", (nth % p).cast("int").alias("part"))


def block_parts(neurons: DataFrame, p: int) -> DataFrame:
    rows = neurons.filter("layer > 0")
    return rows.select("layer", "neuron", (F.ntile(p).over(Window.partitionBy("layer").orderBy("neuron")) - 1).cast("int").alias("part"))


def assign_inputs(weights: DataFrame, inputs: DataFrame, parts: DataFrame, p: int, rule: str = "most_pins", seed: int = 42) -> DataFrame:
    """(layer 0, neuron, part): each input goes to a part that reads it. Inputs that nobody reads are dealt by hash.

    most_pins: the part with most readers, ties to the lowest; lowest: the lowest part; balanced: one of the readers' parts by hash.
    """
    rows = parts.filter("layer = 1").select(F.col("neuron").alias("row"), "part")
    pins = weights.filter("layer = 1").join(rows, "row").groupBy(F.col("col").alias("neuron"), "part").agg(F.count(F.lit(1)).alias("n"))
    order = {"most_pins": [F.desc("n"), "part"], "lowest": ["part"], "balanced": [portable_hash(F.col("neuron"), F.col("part"), seed), "part"]}[rule]
    best = pins.withColumn("nth", F.row_number().over(Window.partitionBy("neuron").orderBy(*order))).filter("nth = 1").select("neuron", "part")
    spare = (portable_hash(0, F.col("neuron"), seed) % p).cast("int")
    return inputs.join(best, "neuron", "left").select(F.lit(0).alias("layer"), "neuron", F.coalesce("part", spare).alias("part"))


def with_inputs(net: Network, parts: DataFrame, p: int, rule: str = "most_pins") -> DataFrame:
    return assign_inputs(net.weights, net.of_layer(0), parts, p, rule).unionByName(parts)


def capacities(weights: DataFrame, p: int, eps: float = 0.01, shares: list[float] | None = None) -> DataFrame:
    """(layer, part, capacity, feasible): the load a part may take. A bound below the heaviest row (or below one row a part) is raised to it."""
    return row_capacities(weights.groupBy("layer", "row").agg(F.count(F.lit(1)).alias("n")), p, eps, shares)


def row_capacities(rows: DataFrame, p: int, eps: float = 0.01, shares: list[float] | None = None) -> DataFrame:
    """capacities() from the links of each row: rows (layer, row, n)."""
    shares = shares or [1.0] * p
    total = sum(shares)
    sums = rows.groupBy("layer").agg(F.sum("n").alias("all"), F.max("n").alias("heaviest"), F.count(F.lit(1)).alias("rows"))
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("part"), F.lit(s / total).alias("share")) for m, s in enumerate(shares)])).alias("s")
    out = sums.select("layer", "all", "heaviest", "rows", each)
    bound = F.floor(F.round(F.col("all") * F.col("s.share") * (1 + eps), 6))
    return out.select("layer", "s.part", F.greatest(bound, "heaviest").cast("bigint").alias("capacity"), ((bound >= F.col("heaviest")) & (F.col("rows") >= p)).alias("feasible"))


def block_order(parts: DataFrame) -> DataFrame:
    """(layer, neuron, part, position): rows renumbered so that each part is a block."""
    return parts.withColumn("position", F.row_number().over(Window.partitionBy("layer").orderBy("part", "neuron")) - 1)


def fixed_pins(weights: DataFrame, parts: DataFrame, layer: int) -> DataFrame:
    """(net, part): the owner of each net's input, fixed with weight 0 in the layer's hypergraph."""
    owners = parts.filter(F.col("layer") == layer - 1).select(F.col("neuron").alias("net"), "part")
    return weights.filter(F.col("layer") == layer).select(F.col("col").alias("net")).distinct().join(owners, "net")


def layer_hypergraph(weights: DataFrame, layer: int, parts: DataFrame | None = None, weight: str = "links", cost: int = 2) -> dict[str, DataFrame]:
    """vertices (v, weight), nets (net, cost) and pins (net, v, part, is_fixed) of one layer, as views over the weights."""
    w = weights.filter(F.col("layer") == layer)
    links = F.count(F.lit(1)) if weight == "links" else F.lit(1).cast("bigint")
    pins = w.select(F.col("col").alias("net"), F.col("row").alias("v"), F.lit(None).cast("int").alias("part"), F.lit(False).alias("is_fixed"))
    if parts is not None and layer > 1:
        pins = pins.unionByName(fixed_pins(weights, parts, layer).select("net", F.lit(None).cast("bigint").alias("v"), "part", F.lit(True).alias("is_fixed")))
    return {"vertices": w.groupBy(F.col("row").alias("v")).agg(links.alias("weight")), "nets": w.select(F.col("col").alias("net")).distinct().withColumn("cost", F.lit(cost)), "pins": pins}


def group_parts(parts: DataFrame, cores: int) -> DataFrame:
    """Parts of one node as one: for measures that count words between nodes only."""
    return parts.withColumn("part", F.floor(F.col("part") / cores).cast("int"))


def seed_from_inputs(weights: DataFrame, parts: DataFrame, layer: int, p: int, caps: DataFrame) -> DataFrame:
    """(neuron, part): rows to the part that owns most of their inputs, as far as its capacity goes; the rest is dealt in turn."""
    owner = parts.filter(F.col("layer") == layer - 1).select(F.col("neuron").alias("col"), "part")
    w = weights.filter(F.col("layer") == layer)
    pull = w.join(owner, "col").groupBy("row", "part").agg(F.count(F.lit(1)).alias("pull"))
    weight = w.groupBy("row").agg(F.count(F.lit(1)).alias("n"))
    return seed_by_pull(pull, weight, p, caps.filter(F.col("layer") == layer).select("part", "capacity"))


def seed_by_pull(pull: DataFrame, weight: DataFrame, p: int, cap: DataFrame) -> DataFrame:
    """seed_from_inputs() of one layer from pull (row, part, pull), the inputs of a row that a part owns, and weight (row, n)."""
    best = pull.groupBy("row").agg(F.max_by(F.struct("part", "pull"), F.struct("pull", -F.col("part"))).alias("b"))
    have = weight.join(best, "row", "left").select("row", "n", "b.part", "b.pull")
    run = F.sum("n").over(Window.partitionBy("part").orderBy(F.desc("pull"), "row").rowsBetween(Window.unboundedPreceding, 0))
    placed = have.withColumn("run", run).join(F.broadcast(cap), "part", "left")
    fits = placed.filter("run <= capacity").select(F.col("row").alias("neuron"), "part")
    rest = have.join(fits, have.row == fits.neuron, "left_anti")
    left = cap.join(placed.filter("run <= capacity").groupBy("part").agg(F.sum("n").alias("used")), "part", "left")
    slots = left.withColumn("room", F.greatest(F.lit(0), F.col("capacity") - F.coalesce("used", F.lit(0))))
    # fill the free room in part order: positions on one line of load
    line = slots.withColumn("to", F.sum("room").over(Window.partitionBy(F.lit(0)).orderBy("part"))).withColumn("from", F.col("to") - F.col("room")).withColumnRenamed("part", "free")
    at = rest.withColumn("at", F.sum("n").over(Window.partitionBy(F.lit(0)).orderBy("row")) - F.col("n"))
    dealt = at.join(F.broadcast(line), (F.col("at") >= F.col("from")) & (F.col("at") < F.col("to")), "left")
    return fits.unionByName(dealt.select(F.col("row").alias("neuron"), F.coalesce("free", (F.col("row") % p).cast("int")).alias("part")))


def seed_by_signature(weights: DataFrame, layer: int, p: int, hashes: int = 2) -> DataFrame:
    """(neuron, part): rows sorted by minwise hashes of their inputs and cut into p ranges of equal load."""
    w = weights.filter(F.col("layer") == layer)
    sig = [F.min(F.xxhash64("col", F.lit(i))).alias(f"s{i}") for i in range(hashes)]
    rows = w.groupBy("row").agg(F.count(F.lit(1)).alias("n"), *sig)
    # load before each signature bucket, then inside the bucket: no window spans the whole layer
    rows = rows.withColumn("bucket", F.shiftright("s0", 54))
    per = rows.groupBy("bucket").agg(F.sum("n").alias("held"))
    ahead = per.withColumn("ahead", F.sum("held").over(Window.partitionBy(F.lit(0)).orderBy("bucket")) - F.col("held"))  # 1,024 buckets
    rows = rows.join(F.broadcast(ahead), "bucket")
    order = Window.partitionBy("bucket").orderBy(*[f"s{i}" for i in range(hashes)], "row").rowsBetween(Window.unboundedPreceding, 0)
    at = F.col("ahead") + F.sum("n").over(order) - F.col("n")
    total = w.count()
    return rows.select(F.col("row").alias("neuron"), F.least(F.lit(p - 1), F.floor(at * p / F.lit(max(total, 1)))).cast("int").alias("part"))
