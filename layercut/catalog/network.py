"""Queries on encodings, topologies and the passes."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import portable_hash
from ..operators import encode, passes, topology
from ..operators.partition import random_parts, with_inputs
from ..operators.routes import send_map
from ..plans import inference
from ..plans.sharded import Sharded, all_links, backward_sharded, forward_sharded, partials_by_part
from ..sources.generators import init_weights, mixed_radix, register_generators
from ..session import cut_lineage
from ..sources.tables import read_table
from .base import H, RADIX, SEED, TRADE, TRADE_EDGES, TRADE_NEURONS, TRADE_X, TRADE_Y, P, forward_sql, query, r6, radix_sql

PIX = "SELECT vec_id, i - 1 AS px, embedding[i]::DOUBLE AS v FROM embeddings, range(1, 65) t(i)"
KERNEL = [[1.0, 2.0, 1.0], [2.0, 4.0, 2.0], [1.0, 2.0, 1.0]]
TRADE_CTES = f"WITH {TRADE}, {TRADE_NEURONS}, {TRADE_X}, {TRADE_Y}"
N8, L8, D8 = 64, 4, 8  # the small generated network that reads 8 x 8 images
IMG = f"ix AS (SELECT vec_id, px AS neuron, 1.0::DOUBLE AS x FROM ({PIX}) WHERE v > 0)"
RN = lambda n, layers: f"rn AS (SELECT l.range::INTEGER AS layer, n.range AS neuron FROM range({layers + 1}) l, range({n}) n)"
IMG_CTES = f"WITH {radix_sql(N8, L8, D8)}, {RN(N8, L8)}, {IMG}"


def images(spark, sf_dir: str, side: int = 8) -> DataFrame:
    return encode.encode_images(read_table(spark, sf_dir, "embeddings"), side)


def image_net(spark, kind: str):
    return topology.radix_network(spark, N8, L8, D8, kind)


def digits(spark, sf_dir: str) -> DataFrame:
    """y over the 64 outputs: the label's neuron."""
    return encode.one_hot_targets(read_table(spark, sf_dir, "embeddings"))


# ---- encodings
@query("encode_embedding_binary", f"SELECT vec_id, px AS neuron, 1.0::DOUBLE AS x FROM ({PIX}) WHERE v > 0")
def _(spark, d):
    return images(spark, d)


@query("encode_embedding_upsampled_16", f"SELECT vec_id, ((px // 8 * 2 + dy.range) * 16 + px % 8 * 2 + dx.range)::BIGINT AS neuron, 1.0::DOUBLE AS x FROM ({PIX}), range(2) dy, range(2) dx WHERE v > 0")
def _(spark, d):
    return images(spark, d, 16)


@query("encode_targets_onehot", "SELECT vec_id, label::BIGINT AS neuron, 1.0::DOUBLE AS y FROM embeddings")
def _(spark, d):
    return digits(spark, d)


@query("encode_trade_months", f"WITH {TRADE_X} SELECT * FROM tx")
def _(spark, d):
    return encode.trade_months(spark, d)


@query("encode_trade_targets", f"WITH {TRADE_Y} SELECT * FROM ty")
def _(spark, d):
    return encode.trade_targets(spark, d)


@query(
    "encode_doc_tokens_hashed",
    f"""SELECT DISTINCT doc_id AS vec_id, {H('word', "'token'", 0)} % 1024 AS neuron, 1.0::DOUBLE AS x FROM (SELECT doc_id, unnest(string_split_regex(lower(coalesce(text, '')), '[ \t\n\x0b\x0c\r]+')) AS word FROM documents) WHERE word <> ''""",
)
def _(spark, d):
    return encode.hashed_tokens(read_table(spark, d, "documents"))


@query(
    "encode_event_windows",
    "SELECT DISTINCT user_id * 1000 + date_diff('day', DATE '2024-01-01', ts::DATE) AS vec_id, ((list_position(['signup', 'view', 'purchase', 'error', 'click'], event_type) - 1) * 24 + hour(ts))::BIGINT AS neuron, 1.0::DOUBLE AS x FROM events WHERE event_type IN ('signup', 'view', 'purchase', 'error', 'click')",
)
def _(spark, d):
    return encode.event_windows(read_table(spark, d, "events"))


@query("encode_doc_labels", "SELECT doc_id AS vec_id, 0::BIGINT AS neuron, quality::DOUBLE AS y FROM labels UNION ALL SELECT doc_id, 1, toxic::DOUBLE FROM labels")
def _(spark, d):
    return encode.doc_targets(read_table(spark, d, "labels"))


@query("encode_page_features", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, length(regexp_replace(coalesce(html, ''), '<[^>]*>', '', 'g')) AS n_text, len(string_split(html, '<'))::BIGINT AS n_tags FROM pages")
def _(spark, d):
    return encode.encode_pages(read_table(spark, d, "pages"))


# ---- topologies
@query("trade_network_edges", f'WITH {TRADE} SELECT layer, "row", col, w FROM tw')
def _(spark, d):
    return topology.trade_network(spark, d).weights


@query("trade_layer_shapes", f'SELECT layer, count(*) AS links, count(DISTINCT "row") AS n_rows, count(DISTINCT col) AS n_cols FROM ({TRADE_EDGES}) GROUP BY layer')
def _(spark, d):
    return topology.trade_edges(spark, d).groupBy("layer").agg(F.count(F.lit(1)).alias("links"), F.count_distinct("row").alias("n_rows"), F.count_distinct("col").alias("n_cols"))


@query("radix_network_edges", f'WITH {radix_sql(*RADIX)} SELECT layer, "row", col, w FROM rw')
def _(spark, d):
    return topology.radix_network(spark, RADIX[0], RADIX[1], RADIX[2]).weights


@query("radix_degree_check", f'WITH {radix_sql(*RADIX)} SELECT layer, min(n) AS least, max(n) AS most FROM (SELECT layer, "row", count(DISTINCT col) AS n FROM rw GROUP BY 1, 2) GROUP BY layer')
def _(spark, d):
    by = mixed_radix(spark, RADIX[0], RADIX[1], RADIX[2]).groupBy("layer", "row").agg(F.count_distinct("col").alias("n"))
    return by.groupBy("layer").agg(F.min("n").alias("least"), F.max("n").alias("most"))


_TAPS = ", ".join(f"({i}, {j}, {KERNEL[i][j]}::DOUBLE)" for i in range(3) for j in range(3))
CONV_SQL = f'cw AS (SELECT r.range AS "row", ((r.range // 8 + t.i - 1) * 8 + r.range % 8 + t.j - 1)::BIGINT AS col, t.w FROM range(64) r, (VALUES {_TAPS}) AS t(i, j, w) WHERE r.range // 8 + t.i - 1 BETWEEN 0 AND 7 AND r.range % 8 + t.j - 1 BETWEEN 0 AND 7)'
POOL_SQL = 'aw AS (SELECT ((range // 8) // 2 * 4 + (range % 8) // 2)::BIGINT AS "row", range AS col, 0.25::DOUBLE AS w FROM range(64))'


def lit_sql(links: str) -> str:
    """links (a CTE) and how many images light the pixel that each reads."""
    return f"SELECT l.*, coalesce(i.images, 0)::BIGINT AS images FROM {links} l LEFT JOIN (SELECT neuron, count(*) AS images FROM ix GROUP BY 1) i ON i.neuron = l.col"


def lit_links(links: DataFrame, x: DataFrame) -> DataFrame:
    lit = x.groupBy(F.col("neuron").alias("col")).agg(F.count(F.lit(1)).alias("images"))
    return links.join(lit, "col", "left").select(*links.columns, F.coalesce("images", F.lit(0)).alias("images"))


@query("conv_layer_edges", f"WITH {CONV_SQL}, {IMG} {lit_sql('cw')}")
def _(spark, d):
    return lit_links(topology.conv_layer(spark, KERNEL, 8, 8, 1, 1), images(spark, d))


@query("avgpool_layer_edges", f"WITH {POOL_SQL}, {IMG} {lit_sql('aw')}")
def _(spark, d):
    return lit_links(topology.avg_pool_layer(spark, 8, 8), images(spark, d))


_PRUNE = 'SELECT layer, "row", col, w FROM (SELECT *, row_number() OVER ({over} ORDER BY abs(w), layer, "row", col) AS nth, count(*) OVER ({over}) AS n FROM rw) WHERE nth > floor(n * {s})'


@query("prune_by_magnitude_layer", f"WITH {radix_sql(*RADIX)} {_PRUNE.format(over='PARTITION BY layer', s='0.9::DOUBLE')}")
def _(spark, d):
    return topology.prune(topology.radix_network(spark, RADIX[0], RADIX[1], RADIX[2]).weights, 0.9)


@query("prune_global", f"WITH {radix_sql(*RADIX)} {_PRUNE.format(over='', s='0.5::DOUBLE')}")
def _(spark, d):
    return topology.prune(topology.radix_network(spark, RADIX[0], RADIX[1], RADIX[2]).weights, 0.5, "global")


@query("prune_by_sketch")
def _(spark, d):
    return topology.prune(topology.radix_network(spark, RADIX[0], RADIX[1], RADIX[2], form="uniform").weights, 0.9, exact=False)


@query("init_weights_uniform")
def _(spark, d):
    return init_weights(mixed_radix(spark, RADIX[0], RADIX[1], RADIX[2]), form="uniform")


BIAS_SQL = f'bs AS (SELECT layer, neuron AS "row", ({H("layer", "neuron", 3)} % 17 - 8) / 16.0::DOUBLE AS b FROM tn WHERE layer > 0)'


def _bias(neurons):
    return neurons.filter("layer > 0").select("layer", F.col("neuron").alias("row"), ((portable_hash(F.col("layer"), F.col("neuron"), 3) % 17 - 8) / F.lit(16.0)).alias("b"))


@query("fold_bias_edges", f'WITH {TRADE}, {TRADE_NEURONS}, {BIAS_SQL} SELECT layer, "row", col, w FROM tw UNION ALL SELECT layer, "row", -1, b FROM bs')
def _(spark, d):
    net = topology.trade_network(spark, d)
    return topology.fold_bias(net.weights, _bias(net.neurons))


@query("reachability_recursive", f"""WITH RECURSIVE te AS ({TRADE_EDGES}), back(layer, neuron) AS (SELECT 4, 1::BIGINT UNION SELECT b.layer - 1, e.col FROM back b JOIN te e ON e.layer = b.layer AND e."row" = b.neuron WHERE b.layer > 2) SELECT layer, neuron FROM back""")
def _(spark, d):
    edges = topology.trade_edges(spark, d).filter("layer > 2")
    return topology.reachable(spark, edges, 4, 1)


# ---- forward
def _trade(spark, d, kind):
    return topology.trade_network(spark, d, kind), encode.trade_months(spark, d)


@query("spmv_layer1_trade", f'WITH {TRADE}, {TRADE_X} SELECT a.vec_id, w."row" AS neuron, sum(w.w * a.x) AS z FROM tw w JOIN tx a ON w.col = a.neuron WHERE w.layer = 1 GROUP BY 1, 2')
def _(spark, d):
    net, x = _trade(spark, d, "relu")
    return passes.spmv(net.layer(1), x)


@query("spmv_layer2_trade", f'WITH {TRADE}, ox AS (SELECT DISTINCT 0::BIGINT AS vec_id, l_partkey AS neuron, 1.0::DOUBLE AS x FROM lineitem) SELECT a.vec_id, w."row" AS neuron, sum(w.w * a.x) AS z FROM tw w JOIN ox a ON w.col = a.neuron WHERE w.layer = 2 GROUP BY 1, 2')
def _(spark, d):
    net, _ = _trade(spark, d, "relu")
    ones = net.layer(2).select(F.lit(0).cast("bigint").alias("vec_id"), F.col("col").alias("neuron"), F.lit(1.0).alias("x")).distinct()
    return passes.spmv(net.layer(2), ones, "merge")


def _forward_oracle(kind: str, bias: bool = False) -> str:
    b = f", {BIAS_SQL}" if bias else ""
    return f"WITH {TRADE}, {TRADE_NEURONS}, {TRADE_X}{b}, {forward_sql('tw', 'tn', 'tx', 4, kind, 'bs' if bias else None)} SELECT vec_id, neuron, round(x, 6) AS x FROM a4"


for _kind in ("sigmoid", "tanh"):

    @query(f"forward_trade_{_kind}" if _kind == "sigmoid" else "forward_tanh", _forward_oracle(_kind) + ("" if _kind == "sigmoid" else " WHERE abs(z) > 0"))
    def _(spark, d, kind=_kind):
        net, x = _trade(spark, d, kind)
        out = passes.last_layer(net, x)
        return (out if kind == "sigmoid" else out.filter("abs(z) > 0")).select("vec_id", "neuron", r6("x").alias("x"))


@query("forward_trade_relu", _forward_oracle("relu") + " WHERE x <> 0")
def _(spark, d):
    net, x = _trade(spark, d, "relu")
    return passes.last_layer(net, x).filter("x <> 0").select("vec_id", "neuron", r6("x").alias("x"))


@query("forward_with_bias", _forward_oracle("sigmoid", True))
def _(spark, d):
    net, x = _trade(spark, d, "sigmoid")
    net = net.with_weights(topology.fold_bias(net.weights, _bias(net.neurons)))
    return passes.forward(net, x, folded=True).filter("layer = 4").select("vec_id", "neuron", r6("x").alias("x"))


@query("forward_with_bias_vector", _forward_oracle("sigmoid", True))
def _(spark, d):
    net, x = _trade(spark, d, "sigmoid")
    return passes.forward(net, x, bias=_bias(net.neurons)).filter("layer = 4").select("vec_id", "neuron", r6("x").alias("x"))


@query("forward_radix_relu", f"{IMG_CTES}, {forward_sql('rw', 'rn', 'ix', L8, 'relu')} SELECT vec_id, neuron, round(x, 6) AS x FROM a{L8} WHERE x <> 0")
def _(spark, d):
    return passes.last_layer(image_net(spark, "relu"), images(spark, d)).filter("x <> 0").select("vec_id", "neuron", r6("x").alias("x"))


@query("forward_radix_sigmoid_batch", f"{IMG_CTES}, {forward_sql('rw', 'rn', 'ix', L8, 'sigmoid')} SELECT vec_id, neuron, round(x, 6) AS x FROM a{L8}")
def _(spark, d):
    return passes.last_layer(image_net(spark, "sigmoid"), images(spark, d)).select("vec_id", "neuron", r6("x").alias("x"))


@query(
    "forward_conv_pool",
    f"""WITH {CONV_SQL}, {POOL_SQL}, {IMG}, c AS (SELECT vec_id, "row" AS neuron, sum(w * x) AS x FROM cw JOIN ix ON col = neuron GROUP BY 1, 2)
SELECT vec_id, "row" AS neuron, sum(w * x) AS z FROM aw JOIN c ON col = neuron GROUP BY 1, 2""",
)
def _(spark, d):
    c = passes.spmv(topology.conv_layer(spark, KERNEL, 8, 8, 1, 1), images(spark, d)).withColumnRenamed("z", "x")
    return passes.spmv(topology.avg_pool_layer(spark, 8, 8), c)


@query("max_pool_grouped", f"SELECT vec_id, ((px // 8) // 2 * 4 + (px % 8) // 2)::BIGINT AS neuron, max(v) AS x FROM ({PIX}) GROUP BY 1, 2")
def _(spark, d):
    px = read_table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("neuron", "v")).select("vec_id", "neuron", F.col("v").cast("double").alias("x"))
    return topology.max_pool(px, 8)


def sharded_trade(spark, d, kind: str = "sigmoid", p: int = P) -> Sharded:
    net = topology.trade_network(spark, d, kind)
    return Sharded.of(net, random_parts(net.neurons, p, SEED), p)


@query("forward_sharded_trade", _forward_oracle("sigmoid"))
def _(spark, d):
    x = encode.trade_months(spark, d)
    return forward_sharded(sharded_trade(spark, d), x, x.select("vec_id").distinct()).select("vec_id", "neuron", r6("x").alias("x"))


@query("forward_sharded_overlap", _forward_oracle("relu") + " WHERE x <> 0")
def _(spark, d):
    x = encode.trade_months(spark, d)
    return forward_sharded(sharded_trade(spark, d, "relu"), x, x.select("vec_id").distinct(), overlap=True).filter("x <> 0").select("vec_id", "neuron", r6("x").alias("x"))


@query("forward_sharded_equals_plain", "SELECT 0::BIGINT AS differing")
def _(spark, d):
    net = image_net(spark, "sigmoid")
    x = images(spark, d)
    vs = x.select("vec_id").distinct()
    a = forward_sharded(Sharded.of(net, random_parts(net.neurons, P, SEED), P), x, vs).select("vec_id", "neuron", "x")
    b = passes.last_layer(net, x, vs).select("vec_id", "neuron", F.col("x").alias("plain"))
    far = F.coalesce(F.abs(F.col("x") - F.col("plain")) > 1e-9, F.lit(True))
    return a.join(b, ["vec_id", "neuron"], "full").agg(F.count_if(far).alias("differing"))


@query("sparse_vs_dense_forward", "SELECT 0::BIGINT AS differing, (SELECT count(*) * 64 FROM embeddings) AS compared")
def _(spark, d):
    """All images through a network of their own width, its absent links once left out and once held as zeros."""
    net = topology.radix_network(spark, 64, 2, 8, "sigmoid")
    x = images(spark, d, 8)
    vs = x.select("vec_id").distinct()
    a = passes.last_layer(net, x, vs).select("vec_id", "neuron", "x")
    b = passes.dense_forward(net, x, vs).withColumnRenamed("x", "dense")
    far = F.coalesce(F.abs(F.col("x") - F.col("dense")) > 1e-9, F.lit(True))
    return a.join(b, ["vec_id", "neuron"], "full").agg(F.count_if(far).alias("differing"), F.count(F.lit(1)).alias("compared"))


@query("weight_medians_pandas", f"WITH {radix_sql(*RADIX)} SELECT layer, median(w) AS median_w FROM rw GROUP BY 1")
def _(spark, d):
    """A grouped aggregate that Spark runs in pandas."""

    @F.pandas_udf("double")
    def median(w: pd.Series) -> float:
        return float(w.median())

    return topology.radix_network(spark, *RADIX).weights.groupBy("layer").agg(median("w").alias("median_w"))


@query("layer_fans_table_function", f'WITH {radix_sql(*RADIX)}, f AS (SELECT layer, "row", count(*) AS n FROM rw GROUP BY 1, 2) SELECT layer, sum(n)::BIGINT AS links, max(n)::BIGINT AS widest FROM f GROUP BY 1')
def _(spark, d):
    """A table function over a table argument, a partition a layer."""
    register_generators(spark)
    topology.radix_network(spark, *RADIX).weights.select("layer", "row").createOrReplaceTempView("fan_links")
    return spark.sql("SELECT * FROM layer_fans(TABLE(fan_links) PARTITION BY layer ORDER BY row)")


# ---- backward
def _prime(z: str, x: str, kind: str) -> str:
    return {"sigmoid": f"{x} * (1 - {x})", "relu": f"(CASE WHEN {z} > 0 THEN 1.0 ELSE 0.0 END)"}[kind]


def backward_sql(weights: str, depth: int, y: str, kind: str) -> str:
    """CTEs d<depth> ... d1 (vec_id, neuron, delta)."""
    out = [f"d{depth} AS (SELECT a.vec_id, a.neuron, (a.x - coalesce(t.y, 0)) * {_prime('a.z', 'a.x', kind)} AS delta FROM a{depth} a LEFT JOIN {y} t ON t.vec_id = a.vec_id AND t.neuron = a.neuron)"]
    for k in range(depth, 1, -1):
        out.append(f'd{k - 1} AS (SELECT s.vec_id, s.neuron, s.s * {_prime("a.z", "a.x", kind)} AS delta FROM (SELECT d.vec_id, w.col AS neuron, sum(w.w * d.delta) AS s FROM {weights} w JOIN d{k} d ON w."row" = d.neuron WHERE w.layer = {k} GROUP BY 1, 2) s JOIN a{k - 1} a ON a.vec_id = s.vec_id AND a.neuron = s.neuron)')
    return ", ".join(out)


ETA = 0.01
IY = "iy AS (SELECT vec_id, label::BIGINT AS neuron, 1.0::DOUBLE AS y FROM embeddings)"
IMG_PASSES = f"{IMG_CTES}, {IY}, {forward_sql('rw', 'rn', 'ix', L8, 'sigmoid')}, {backward_sql('rw', L8, 'iy', 'sigmoid')}"


def update_sql(weights: str, depth: int, x: str, divide: str = "1") -> str:
    """CTE nw (layer, row, col, w) after one step."""
    grads = " UNION ALL ".join(
        f'SELECT {k} AS layer, w."row", w.col, sum(d.delta * v.x) AS g FROM {weights} w JOIN d{k} d ON d.neuron = w."row" JOIN {x if k == 1 else f"a{k - 1}"} v ON v.vec_id = d.vec_id AND v.neuron = w.col WHERE w.layer = {k} GROUP BY 2, 3'
        for k in range(1, depth + 1)
    )
    return f'gr AS ({grads}), nw AS (SELECT w.layer, w."row", w.col, w.w - {ETA} * coalesce(g.g, 0) / {divide} AS w FROM {weights} w LEFT JOIN gr g ON g.layer = w.layer AND g."row" = w."row" AND g.col = w.col)'


@query("output_delta_mse", f"{TRADE_CTES}, {forward_sql('tw', 'tn', 'tx', 4, 'sigmoid')}, {backward_sql('tw', 4, 'ty', 'sigmoid').split(', d3 AS')[0]} SELECT vec_id, neuron, round(delta, 6) AS delta FROM d4")
def _(spark, d):
    net, x = _trade(spark, d, "sigmoid")
    return passes.output_delta(passes.last_layer(net, x), encode.trade_targets(spark, d), "sigmoid").select("vec_id", "neuron", r6("delta").alias("delta"))


@query("back_step_layer", f"{IMG_PASSES} SELECT vec_id, neuron, round(delta, 6) AS delta FROM d{L8 - 1}")
def _(spark, d):
    g = passes.gradients(image_net(spark, "sigmoid"), images(spark, d), digits(spark, d))
    return g.filter(F.col("layer") == L8 - 1).select("vec_id", "neuron", r6("delta").alias("delta"))


@query("backward_all_deltas", " UNION ALL ".join([f"{IMG_PASSES} SELECT 1 AS layer, vec_id, neuron, round(delta, 6) AS delta FROM d1", *[f"SELECT {k}, vec_id, neuron, round(delta, 6) FROM d{k}" for k in range(2, L8 + 1)]]))
def _(spark, d):
    g = passes.gradients(image_net(spark, "sigmoid"), images(spark, d), digits(spark, d))
    return g.select("layer", "vec_id", "neuron", r6("delta").alias("delta"))


@query("weight_gradient_masked", f'{IMG_PASSES} SELECT w."row", w.col, round(sum(d.delta * v.x), 6) AS g FROM rw w JOIN d1 d ON d.neuron = w."row" JOIN ix v ON v.vec_id = d.vec_id AND v.neuron = w.col WHERE w.layer = 1 GROUP BY 1, 2')
def _(spark, d):
    net, x = image_net(spark, "sigmoid"), images(spark, d)
    delta = passes.gradients(net, x, digits(spark, d)).filter("layer = 1")
    return passes.weight_grad(net.layer(1), delta, x).select("row", "col", r6("g").alias("g"))


@query("update_one_step", f'{IMG_PASSES}, {update_sql("rw", L8, "ix")} SELECT layer, "row", col, round(w, 6) AS w FROM nw')
def _(spark, d):
    return passes.step(image_net(spark, "sigmoid"), images(spark, d), digits(spark, d), ETA).weights.select("layer", "row", "col", r6("w").alias("w"))


@query("minibatch_exact_step", f'{IMG_PASSES}, {update_sql("rw", L8, "ix", "(SELECT count(DISTINCT vec_id) FROM ix)")} SELECT layer, "row", col, round(w, 8) AS w FROM nw')
def _(spark, d):
    x = images(spark, d)
    n = x.select("vec_id").distinct().count()
    return passes.step(image_net(spark, "sigmoid"), x, digits(spark, d), ETA, n).weights.select("layer", "row", "col", F.round("w", 8).alias("w"))


def _averaged_oracle() -> str:
    n = "(SELECT count(DISTINCT vec_id) FROM ix)"
    means = [f"m0 AS (SELECT neuron, sum(x) / {n} AS x FROM ix GROUP BY 1)"] + [f"m{k} AS (SELECT neuron, sum(x) / {n} AS x, sum(x * (1 - x)) / {n} AS slope FROM a{k} GROUP BY 1)" for k in range(1, L8)]
    back = [f"e{L8} AS (SELECT neuron, sum(delta) / {n} AS delta FROM d{L8} GROUP BY 1)"]
    for k in range(L8, 1, -1):
        back.append(f'e{k - 1} AS (SELECT s.neuron, s.s * m.slope AS delta FROM (SELECT w.col AS neuron, sum(w.w * e.delta) AS s FROM rw w JOIN e{k} e ON w."row" = e.neuron WHERE w.layer = {k} GROUP BY 1) s JOIN m{k - 1} m USING (neuron))')
    new = " UNION ALL ".join(f'SELECT {k} AS layer, w."row", w.col, round(w.w - {ETA} * coalesce(e.delta * m.x, 0), 8) AS w FROM rw w LEFT JOIN e{k} e ON e.neuron = w."row" LEFT JOIN m{k - 1} m ON m.neuron = w.col WHERE w.layer = {k}' for k in range(1, L8 + 1))
    return f"{IMG_CTES}, {IY}, {forward_sql('rw', 'rn', 'ix', L8, 'sigmoid')}, {backward_sql('rw', L8, 'iy', 'sigmoid')}, {', '.join(means + back)} {new}"


@query("minibatch_averaged_delta_step", _averaged_oracle())
def _(spark, d):
    x = images(spark, d)
    n = x.select("vec_id").distinct().count()
    return passes.step(image_net(spark, "sigmoid"), x, digits(spark, d), ETA, n, batch_rule="averaged_delta").weights.select("layer", "row", "col", F.round("w", 8).alias("w"))


@query("sharded_step", f'{IMG_PASSES}, {update_sql("rw", L8, "ix")} SELECT layer, "row", col, round(w, 6) AS w FROM nw')
def _(spark, d):
    net, x = image_net(spark, "sigmoid"), images(spark, d)
    sh = Sharded.of(net, random_parts(net.neurons, P, SEED), P)
    weights = all_links(backward_sharded(sh, x, digits(spark, d), x.select("vec_id").distinct(), ETA)[1])
    return weights.select("layer", "row", "col", r6("w").alias("w"))


@query(
    "backward_partials_by_part",
    f"""{IMG_PASSES}, pr AS (SELECT layer, neuron, ({H('layer', 'neuron', SEED)} % {P})::INTEGER AS part FROM rn WHERE layer = {L8})
SELECT p.part, w.col AS neuron, d.vec_id, round(sum(w.w * d.delta), 6) AS s FROM rw w JOIN d{L8} d ON d.neuron = w."row" JOIN pr p ON p.neuron = w."row" WHERE w.layer = {L8} GROUP BY 1, 2, 3""",
)
def _(spark, d):
    net, x = image_net(spark, "sigmoid"), images(spark, d)
    sh = Sharded.of(net, random_parts(net.neurons, P, SEED), P)
    deltas, _ = backward_sharded(sh, x, digits(spark, d), x.select("vec_id").distinct(), ETA)
    return partials_by_part(sh, L8, deltas[L8]).select("part", "neuron", "vec_id", r6("s").alias("s"))


@query("loss_before_after", f"""{IMG_PASSES}, {update_sql("rw", L8, "ix", "(SELECT count(DISTINCT vec_id) FROM ix)")}, {forward_sql('nw', 'rn', 'ix', L8, 'sigmoid').replace('vs AS', 'vt AS', 1).replace(' vs v', ' vt v').replace('z1', 'y1').replace('z2', 'y2').replace('z3', 'y3').replace('z4', 'y4').replace('a1', 'b1').replace('a2', 'b2').replace('a3', 'b3').replace('a4', 'b4')}
SELECT round((SELECT sum((a.x - coalesce(t.y, 0)) ** 2) / 2 / count(DISTINCT a.vec_id) FROM a{L8} a LEFT JOIN iy t ON t.vec_id = a.vec_id AND t.neuron = a.neuron), 6) AS before, round((SELECT sum((a.x - coalesce(t.y, 0)) ** 2) / 2 / count(DISTINCT a.vec_id) FROM b{L8} a LEFT JOIN iy t ON t.vec_id = a.vec_id AND t.neuron = a.neuron), 6) AS after""")
def _(spark, d):
    net, x, y = image_net(spark, "sigmoid"), images(spark, d), digits(spark, d)
    n = x.select("vec_id").distinct().count()
    new = passes.step(net, x, y, ETA, n)
    new = new.with_weights(cut_lineage(new.weights))
    mean = lambda m, name: passes.loss_by_vector(passes.last_layer(m, x), y).agg(r6(F.avg("loss")).alias(name))
    return mean(net, "before").crossJoin(mean(new, "after"))  # one row each


# ---- inference
@query("replicated_forward", f"{IMG_CTES}, {forward_sql('rw', 'rn', 'ix', L8, 'sigmoid')} SELECT vec_id, neuron, round(x, 6) AS x FROM a{L8}")
def _(spark, d):
    return inference.infer_replicated(image_net(spark, "sigmoid"), images(spark, d)).select("vec_id", "neuron", r6("x").alias("x"))


@query("block_inference", f"{IMG_CTES}, {forward_sql('rw', 'rn', 'ix', L8, 'sigmoid')} SELECT vec_id, neuron, round(x, 6) AS x FROM a{L8}")
def _(spark, d):
    net, x = image_net(spark, "sigmoid"), images(spark, d)
    full = cut_lineage(with_inputs(net, random_parts(net.neurons, P, SEED), P))
    return inference.infer_blocks(net, x, full, cut_lineage(send_map(net.weights, full)), P).select("vec_id", "neuron", r6("x").alias("x"))


_LABELS = f"{IMG_CTES}, {forward_sql('rw', 'rn', 'ix', L8, 'sigmoid')}, lb AS (SELECT vec_id, neuron AS predicted FROM (SELECT vec_id, neuron, row_number() OVER (PARTITION BY vec_id ORDER BY round(x, 9) DESC, neuron) AS nth FROM a{L8} WHERE neuron < 10) WHERE nth = 1)"


def _labels(spark, d):
    out = passes.last_layer(image_net(spark, "sigmoid"), images(spark, d)).filter("neuron < 10").withColumn("x", F.round("x", 9))
    return passes.predicted_labels(out)


@query("batch_inference_labels", f"{_LABELS} SELECT vec_id, predicted FROM lb")
def _(spark, d):
    return _labels(spark, d)


@query("accuracy_confusion", f"{_LABELS} SELECT label, predicted, count(*) AS n FROM lb JOIN embeddings USING (vec_id) GROUP BY 1, 2")
def _(spark, d):
    from ..operators.measures import confusion

    return confusion(_labels(spark, d), read_table(spark, d, "embeddings").select("vec_id", "label"))


@query("throughput_edges_counted", f"{IMG_CTES} SELECT (SELECT count(DISTINCT vec_id) FROM ix) * (SELECT count(*) FROM rw) AS edges")
def _(spark, d):
    n = images(spark, d).agg(F.count_distinct("vec_id").alias("vectors"))
    return n.crossJoin(image_net(spark, "sigmoid").weights.agg(F.count(F.lit(1)).alias("links"))).select((F.col("vectors") * F.col("links")).alias("edges"))  # one row each


