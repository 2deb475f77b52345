"""Plain relational passes: the sequential definition of each method, one layer or all."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.activation import activate, activate_prime, keeps_zero, loss_slope, loss_value
from ..session import cut_lineage
from .topology import BIAS, Network


def with_bias_input(x: DataFrame, vectors: DataFrame) -> DataFrame:
    """x with the constant one that a folded bias reads."""
    return x.unionByName(vectors.select("vec_id", F.lit(BIAS).cast("bigint").alias("neuron"), F.lit(1.0).alias("x")))


def spmv(layer: DataFrame, x: DataFrame, hint: str | None = None) -> DataFrame:
    """layer (row, col, w) times x (vec_id, neuron, x): (vec_id, neuron, z), rows without a term left out."""
    side = layer.hint(hint) if hint else layer
    return side.join(x, F.col("col") == F.col("neuron")).groupBy("vec_id", F.col("row").alias("neuron")).agg(F.sum(F.col("w") * F.col("x")).alias("z"))


def fill_layer(z: DataFrame, neurons: DataFrame, vectors: DataFrame, kind: str) -> DataFrame:
    """Totals to activations. Where f(0) is not 0 every neuron of the layer is emitted for every vector (vectors: one batch, broadcast)."""
    if not keeps_zero(kind):
        every = neurons.crossJoin(F.broadcast(vectors))  # the layer's own output size
        z = every.join(z, ["vec_id", "neuron"], "left").select("vec_id", "neuron", F.coalesce("z", F.lit(0.0)).alias("z"))
    return z.select("vec_id", "neuron", "z", activate(F.col("z"), kind).alias("x"))


def forward(net: Network, x: DataFrame, vectors: DataFrame | None = None, bias: DataFrame | None = None, folded: bool = False, hint: str | None = None) -> DataFrame:
    """(layer, vec_id, neuron, z, x) of all layers. bias: (layer, row, b) in separate form; folded: the weights hold it as a column."""
    vectors = x.select("vec_id").distinct() if vectors is None else vectors
    out, at = None, x.select("vec_id", "neuron", "x")
    for k in range(1, net.depth + 1):
        z = spmv(net.layer(k), with_bias_input(at, vectors) if folded else at, hint)
        if bias is not None:
            b = bias.filter(F.col("layer") == k).select(F.col("row").alias("neuron"), "b").crossJoin(F.broadcast(vectors))
            z = z.join(b, ["vec_id", "neuron"], "full").select("vec_id", "neuron", (F.coalesce("z", F.lit(0.0)) + F.coalesce("b", F.lit(0.0))).alias("z"))
        acts = fill_layer(z, net.of_layer(k), vectors, net.activation)
        at = acts.select("vec_id", "neuron", "x")
        acts = acts.select(F.lit(k).alias("layer"), "vec_id", "neuron", "z", "x")
        out = acts if out is None else out.unionByName(acts)
    return out


def last_layer(net: Network, x: DataFrame, vectors: DataFrame | None = None, hint: str | None = None) -> DataFrame:
    """(vec_id, neuron, z, x) of the last layer only, in one plan."""
    vectors = x.select("vec_id").distinct() if vectors is None else vectors
    at = x.select("vec_id", "neuron", "x")
    for k in range(1, net.depth + 1):
        acts = fill_layer(spmv(net.layer(k), at, hint), net.of_layer(k), vectors, net.activation)
        at = acts.select("vec_id", "neuron", "x")
    return acts


def dense_forward(net: Network, x: DataFrame, vectors: DataFrame) -> DataFrame:
    """The same with every absent link as a zero: the exact baseline of the tests, quadratic in the layer width."""
    at = net.of_layer(0).crossJoin(vectors).join(x, ["vec_id", "neuron"], "left").select("vec_id", "neuron", F.coalesce("x", F.lit(0.0)).alias("x"))
    for k in range(1, net.depth + 1):
        full = net.of_layer(k).withColumnRenamed("neuron", "row").crossJoin(net.of_layer(k - 1).withColumnRenamed("neuron", "col"))
        full = full.join(net.layer(k), ["row", "col"], "left").select("row", "col", F.coalesce("w", F.lit(0.0)).alias("w"))
        z = spmv(full, at)
        at = z.select("vec_id", "neuron", activate(F.col("z"), net.activation).alias("x"))
    return at


def output_delta(acts: DataFrame, targets: DataFrame, kind: str, loss: str = "mse_half", outputs: int = 1) -> DataFrame:
    """(vec_id, neuron, delta) of the last layer from acts (vec_id, neuron, z, x); absent targets are 0."""
    joined = acts.join(targets, ["vec_id", "neuron"], "left").withColumn("y", F.coalesce("y", F.lit(0.0)))
    return joined.select("vec_id", "neuron", (loss_slope(F.col("x"), F.col("y"), loss, outputs) * activate_prime(F.col("z"), F.col("x"), kind)).alias("delta"))


def back_step(layer: DataFrame, delta: DataFrame, before: DataFrame | None, kind: str) -> DataFrame:
    """delta of the layer before, through the transpose: layer's rows meet delta, its columns are summed. before (vec_id, neuron, z, x) has
    every neuron that can get a delta; without it the sums themselves are returned (gradient of the input)."""
    s = layer.join(delta, F.col("row") == F.col("neuron")).groupBy("vec_id", F.col("col").alias("neuron")).agg(F.sum(F.col("w") * F.col("delta")).alias("s"))
    if before is None:
        return s.filter(F.col("neuron") != BIAS).select("vec_id", "neuron", F.col("s").alias("delta"))
    return s.join(before, ["vec_id", "neuron"]).select("vec_id", "neuron", (F.col("s") * activate_prime(F.col("z"), F.col("x"), kind)).alias("delta"))


def weight_grad(layer: DataFrame, delta: DataFrame, x: DataFrame) -> DataFrame:
    """(row, col, g): the outer product at existing links only, summed over the vectors."""
    d = delta.select("vec_id", F.col("neuron").alias("row"), "delta")
    v = x.select("vec_id", F.col("neuron").alias("col"), "x")
    met = layer.select("row", "col").join(d, "row").join(v, ["vec_id", "col"])
    return met.groupBy("row", "col").agg(F.sum(F.col("delta") * F.col("x")).alias("g"))


def apply_update(layer: DataFrame, grad: DataFrame, eta: float, batch: int = 1) -> DataFrame:
    """layer with w - eta * g / batch; links without a gradient keep their weight."""
    return layer.join(grad, ["row", "col"], "left").select("row", "col", (F.col("w") - F.lit(eta / batch) * F.coalesce("g", F.lit(0.0))).alias("w"))


def gradients(net: Network, x: DataFrame, targets: DataFrame, loss: str = "mse_half", outputs: int = 1, acts: DataFrame | None = None) -> DataFrame:
    """(layer, vec_id, neuron, delta) of all layers."""
    acts = forward(net, x) if acts is None else acts
    of = lambda k: acts.filter(F.col("layer") == k).select("vec_id", "neuron", "z", "x")
    delta = output_delta(of(net.depth), targets, net.activation, loss, outputs)
    out = delta.select(F.lit(net.depth).alias("layer"), "vec_id", "neuron", "delta")
    for k in range(net.depth, 1, -1):
        delta = back_step(net.layer(k), delta, of(k - 1), net.activation)
        out = out.unionByName(delta.select(F.lit(k - 1).alias("layer"), "vec_id", "neuron", "delta"))
    return out


def averaged(acts: DataFrame, keys: list[str]) -> DataFrame:
    """Batch means over the vectors, as one vector 0; absent entries count as zeros of the batch's size given by the caller."""
    return acts.groupBy(*keys).agg(F.avg("x").alias("x"))


def step(net: Network, x: DataFrame, targets: DataFrame, eta: float, batch: int = 1, loss: str = "mse_half", outputs: int = 1, batch_rule: str = "exact") -> Network:
    """One gradient step on the vectors of x. All deltas come from the weights before the step.

    exact: the mean of the vectors' own gradients. averaged_delta: the output deltas are averaged and one vector is sent back; the means of
    the activations and of the activation derivatives over the batch stand in for that vector's.
    """
    acts = cut_lineage(forward(net, x))
    if batch_rule == "averaged_delta":
        of = acts.filter(F.col("layer") == net.depth).select("vec_id", "neuron", "z", "x")
        size = F.lit(float(batch))
        delta = output_delta(of, targets, net.activation, loss, outputs).groupBy("neuron").agg((F.sum("delta") / size).alias("delta"))
        mean = acts.groupBy("layer", "neuron").agg((F.sum("x") / size).alias("x"), (F.sum(activate_prime(F.col("z"), F.col("x"), net.activation)) / size).alias("slope"))
        first = x.groupBy("neuron").agg((F.sum("x") / size).alias("x"))
        made = []
        for k in range(net.depth, 0, -1):
            before = first if k == 1 else mean.filter(F.col("layer") == k - 1)
            one = F.lit(0).cast("bigint").alias("vec_id")
            grad = weight_grad(net.layer(k), delta.select(one, "neuron", "delta"), before.select(one, "neuron", "x"))
            made.append(apply_update(net.layer(k), grad, eta).select(F.lit(k).alias("layer"), "row", "col", "w"))
            if k > 1:
                s = net.layer(k).join(delta, F.col("row") == F.col("neuron")).groupBy(F.col("col").alias("neuron")).agg(F.sum(F.col("w") * F.col("delta")).alias("s"))
                delta = s.join(before, "neuron").select("neuron", (F.col("s") * F.col("slope")).alias("delta"))
    else:
        delta = cut_lineage(gradients(net, x, targets, loss, outputs, acts))
        made = []
        for k in range(1, net.depth + 1):
            before = x if k == 1 else acts.filter(F.col("layer") == k - 1)
            grad = weight_grad(net.layer(k), delta.filter(F.col("layer") == k), before.select("vec_id", "neuron", "x"))
            made.append(apply_update(net.layer(k), grad, eta, batch).select(F.lit(k).alias("layer"), "row", "col", "w"))
    weights = made[0]
    for m in made[1:]:
        weights = weights.unionByName(m)
    return net.with_weights(weights)


def loss_by_vector(acts: DataFrame, targets: DataFrame, kind: str = "mse_half") -> DataFrame:
    """(vec_id, loss) from acts (vec_id, neuron, x) of the last layer."""
    joined = acts.join(targets, ["vec_id", "neuron"], "left").withColumn("y", F.coalesce("y", F.lit(0.0)))
    return joined.groupBy("vec_id").agg(loss_value(F.col("x"), F.col("y"), kind).alias("loss"))


def predicted_labels(acts: DataFrame) -> DataFrame:
    """(vec_id, predicted): the neuron with the largest output, the smallest of equals."""
    return acts.groupBy("vec_id").agg(F.max_by("neuron", F.struct("x", -F.col("neuron"))).alias("predicted"))
