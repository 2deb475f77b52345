"""Queries on partitions, routes and costs."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import portable_hash
from ..operators import cut_aware, measures, partition, routes, topology
from ..operators.encode import trade_months
from ..plans import inference
from ..plans.sharded import Sharded, forward_sharded, placed_inputs, returned_sums
from ..session import cut_lineage, cut_placed
from .base import RADIX, SEED, TRADE, TRADE_NEURONS, H, P, parts_sql, query, r6, radix_sql, routes_sql
from .network import RN, images

RTE = f"WITH {radix_sql(*RADIX)}, {RN(RADIX[0], RADIX[1])}"
CTES = f"WITH {TRADE}, {TRADE_NEURONS}, {parts_sql('te', 'tn')}, {routes_sql('te')}"
RCTES = f"{RTE}, {parts_sql('rw', 'rn')}, {routes_sql('rw')}"


def trade(spark, d):
    net = topology.trade_network(spark, d)
    parts = partition.with_inputs(net, partition.random_parts(net.neurons, P, SEED), P)
    return net, parts


def radix(spark):
    net = topology.radix_network(spark, RADIX[0], RADIX[1], RADIX[2])
    return net, partition.with_inputs(net, partition.random_parts(net.neurons, P, SEED), P)


def hours(spark, d):
    net = topology.hour_network(spark, d)
    return net, partition.with_inputs(net, partition.random_parts(net.neurons, P, SEED), P)


@query("random_partition", f"WITH {TRADE_NEURONS} SELECT layer, neuron, ({H('layer', 'neuron', SEED)} % {P})::INTEGER AS part FROM tn WHERE layer > 0")
def _(spark, d):
    return partition.random_parts(topology.trade_neurons(spark, d), P, SEED)


@query("random_partition_balanced", f"WITH {TRADE_NEURONS} SELECT layer, neuron, ((row_number() OVER (PARTITION BY layer ORDER BY {H('layer', 'neuron', SEED)}, neuron) - 1) % {P})::INTEGER AS part FROM tn WHERE layer > 0")
def _(spark, d):
    return partition.random_parts(topology.trade_neurons(spark, d), P, SEED, balanced=True)


@query("block_partition", f"WITH {TRADE_NEURONS} SELECT layer, neuron, (ntile({P}) OVER (PARTITION BY layer ORDER BY neuron) - 1)::INTEGER AS part FROM tn WHERE layer > 0")
def _(spark, d):
    return partition.block_parts(topology.trade_neurons(spark, d), P)


@query("input_owner_most_pins", f"{CTES} SELECT layer, neuron, part FROM pt WHERE layer = 0")
def _(spark, d):
    return trade(spark, d)[1].filter("layer = 0")


@query("input_owner_lowest", f"""{CTES} SELECT 0 AS layer, n.neuron, coalesce(b.part, ({H(0, 'n.neuron', SEED)} % {P})::INTEGER) AS part FROM tn n LEFT JOIN (SELECT e.col AS neuron, min(p.part) AS part FROM te e JOIN pt p ON p.layer = 1 AND p.neuron = e."row" WHERE e.layer = 1 GROUP BY 1) b USING (neuron) WHERE n.layer = 0""")
def _(spark, d):
    net = topology.trade_network(spark, d)
    return partition.assign_inputs(net.weights, net.of_layer(0), partition.random_parts(net.neurons, P, SEED), P, "lowest")


@query("input_owner_balanced")
def _(spark, d):
    net = topology.trade_network(spark, d)
    return partition.assign_inputs(net.weights, net.of_layer(0), partition.random_parts(net.neurons, P, SEED), P, "balanced")


def _caps_sql(shares: list[float]) -> str:
    values = ", ".join(f"({m}, {s / sum(shares)}::DOUBLE)" for m, s in enumerate(shares))
    return f"""WITH {TRADE} SELECT layer, s.part, greatest(floor(round(n * s.share * 1.01, 6)), heaviest)::BIGINT AS capacity, floor(round(n * s.share * 1.01, 6)) >= heaviest AND n_rows >= {len(shares)} AS feasible
FROM (SELECT layer, sum(k)::DOUBLE AS n, max(k) AS heaviest, count(*) AS n_rows FROM (SELECT layer, "row", count(*) AS k FROM te GROUP BY 1, 2) GROUP BY 1), (VALUES {values}) AS s(part, share)"""


@query("capacities_uniform", _caps_sql([1.0] * P))
def _(spark, d):
    return partition.capacities(topology.trade_network(spark, d).weights, P)


@query("heterogeneous_capacities", _caps_sql([2.0, 1.0, 1.0]))
def _(spark, d):
    return partition.capacities(topology.trade_network(spark, d).weights, 3, shares=[2.0, 1.0, 1.0])


@query("fixed_vertices_layer2", f"{CTES} SELECT DISTINCT e.col AS net, p.part FROM te e JOIN pt p ON p.layer = 1 AND p.neuron = e.col WHERE e.layer = 2")
def _(spark, d):
    net, parts = trade(spark, d)
    return partition.fixed_pins(net.weights, parts, 2)


@query("hypergraph_vertices_nets_pins", f'WITH {TRADE} SELECT layer, count(DISTINCT "row") AS vertices, count(DISTINCT col) AS nets, count(*) + count(DISTINCT col) AS pins FROM te GROUP BY 1')
def _(spark, d):
    return measures.hypergraph_size(topology.trade_network(spark, d).weights)


@query("hypergraph_pins_layer2", f'{CTES} SELECT net, coalesce(v, -1) AS v, coalesce(part, -1) AS part, is_fixed FROM (SELECT col AS net, "row" AS v, NULL::INTEGER AS part, false AS is_fixed FROM te WHERE layer = 2 UNION ALL SELECT DISTINCT e.col, NULL::BIGINT, p.part, true FROM te e JOIN pt p ON p.layer = 1 AND p.neuron = e.col WHERE e.layer = 2)')
def _(spark, d):
    net, parts = trade(spark, d)
    return partition.layer_hypergraph(net.weights, 2, parts)["pins"].na.fill(-1, ["v", "part"])


@query("hypergraph_vertices_layer2", f'WITH {TRADE} SELECT "row" AS v, count(*) AS weight FROM te WHERE layer = 2 GROUP BY 1')
def _(spark, d):
    return partition.layer_hypergraph(topology.trade_network(spark, d).weights, 2)["vertices"]


@query("block_row_order", f"{CTES} SELECT layer, neuron, part, (row_number() OVER (PARTITION BY layer ORDER BY part, neuron) - 1)::INTEGER AS position FROM pt")
def _(spark, d):
    return partition.block_order(trade(spark, d)[1])


@query(
    "move_gains_one_round",
    f"""{RCTES}, pins AS (SELECT e.col AS net, p.part, e."row" FROM rw e JOIN pt p ON p.layer = 2 AND p.neuron = e."row" WHERE e.layer = 2),
hold AS (SELECT net, part FROM pins UNION ALL SELECT DISTINCT e.col, p.part FROM rw e JOIN pt p ON p.layer = 1 AND p.neuron = e.col WHERE e.layer = 2),
cnt AS (SELECT net, part, count(*) AS c FROM hold GROUP BY 1, 2),
tch AS (SELECT p."row", p.part AS own, c.part AS dest, count(*) AS touch, count(*) FILTER (WHERE p.part = c.part AND c.c = 1) AS leave FROM pins p JOIN cnt c USING (net) GROUP BY 1, 2, 3)
SELECT t."row", t.own AS part, t.dest AS "to", (o.leave - (o.touch - t.touch))::BIGINT AS gain FROM tch t JOIN tch o ON o."row" = t."row" AND o.own = o.dest WHERE t.own <> t.dest""",
)
def _(spark, d):
    net, parts = radix(spark)
    pinned = partition.fixed_pins(net.weights, parts, 2)
    links = net.layer(2).select("row", "col")
    return cut_aware.move_gains(links, parts.filter("layer = 2").select(F.col("neuron").alias("row"), "part"), pinned)


@query("cut_aware_partition")
def _(spark, d):
    return cut_aware.cut_aware_parts(hours(spark, d)[0], P)


@query("cut_aware_partition_trade")
def _(spark, d):
    return cut_aware.cut_aware_parts(topology.trade_network(spark, d), P, solver="distributed")


@query("greedy_input_affinity_partition")
def _(spark, d):
    net, parts = hours(spark, d)
    return partition.seed_from_inputs(net.weights, parts, 2, P, partition.capacities(net.weights, P))


@query("signature_order_partition")
def _(spark, d):
    return partition.seed_by_signature(radix(spark)[0].weights, 1, P)


@query("distributed_refinement")
def _(spark, d):
    net, parts = hours(spark, d)
    start = parts.filter("layer = 2").select("neuron", "part")
    return cut_aware.refine_distributed(net.weights, 2, parts.filter("layer = 1"), start, P, partition.capacities(net.weights, P), rounds=3)


@query("cut_aware_beats_random", "SELECT true AS fewer_words, true AS better_balanced, true AS every_row_once")
def _(spark, d):
    """The reported behaviour: fewer words and less imbalance than random placement."""
    from ..session import cut_lineage

    net, base = hours(spark, d)
    own = cut_lineage(partition.with_inputs(net, cut_aware.cut_aware_parts(net, P), P))
    words = lambda parts, name: measures.volume_by_layer(routes.send_map(net.weights, parts)).agg(F.sum("words").alias(name))
    even = lambda parts, name: measures.imbalance(net.weights, parts, P).withColumnRenamed("imbalance", name)
    once = own.groupBy("layer", "neuron").agg(F.count(F.lit(1)).alias("n")).agg((F.max("n") == 1).alias("one"), F.count(F.lit(1)).alias("rows"))
    all_rows = net.neurons.agg(F.count(F.lit(1)).alias("all"))
    row = words(own, "a").crossJoin(words(base, "b")).crossJoin(even(own, "c")).crossJoin(even(base, "e")).crossJoin(once).crossJoin(all_rows)  # one row each
    return row.select((F.col("a") < 0.5 * F.col("b")).alias("fewer_words"), (F.col("c") <= F.col("e")).alias("better_balanced"), (F.col("one") & (F.col("rows") == F.col("all"))).alias("every_row_once"))


# ---- routes and costs
@query("routes_forward", f"{CTES} SELECT layer, neuron, src, dst FROM rt")
def _(spark, d):
    net, parts = trade(spark, d)
    return routes.send_map(net.weights, parts)


@query("routes_backward", f"{CTES} SELECT layer, neuron, dst AS src, src AS dst FROM rt")
def _(spark, d):
    net, parts = trade(spark, d)
    return routes.back_send_map(routes.send_map(net.weights, parts))


@query("routes_received", f"{CTES} SELECT layer, dst AS part, src AS source, neuron FROM rt")
def _(spark, d):
    net, parts = trade(spark, d)
    return routes.recv_map(routes.send_map(net.weights, parts))


@query("messages_by_pair", f"{CTES} SELECT layer, src, dst, array_to_string(list_sort(list(neuron)), ' ') AS entries, count(*) AS words FROM rt WHERE src <> dst GROUP BY 1, 2, 3")
def _(spark, d):
    net, parts = trade(spark, d)
    return routes.messages(routes.send_map(net.weights, parts)).withColumn("entries", F.array_join(F.transform("entries", lambda n: n.cast("string")), " "))


LAM = """lm AS (SELECT layer, net, count(DISTINCT part)::INTEGER AS lam FROM (SELECT e.layer, e.col AS net, p.part FROM te e JOIN pt p ON p.layer = e.layer AND p.neuron = e."row"
UNION ALL SELECT DISTINCT e.layer, e.col, p.part FROM te e JOIN pt p ON p.layer = e.layer - 1 AND p.neuron = e.col) GROUP BY 1, 2)"""


@query("net_connectivity", f"{CTES}, {LAM} SELECT * FROM lm")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.connectivity(net.weights, parts)


@query("lambda_histogram", f"{CTES}, {LAM} SELECT layer, lam, count(*) AS nets FROM lm GROUP BY 1, 2")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.lambda_histogram(net.weights, parts)


@query("cut_size_by_layer", f"{CTES}, {LAM} SELECT layer, count(*) FILTER (WHERE lam > 1) AS cut_nets, (2 * sum(lam - 1))::BIGINT AS cut FROM lm GROUP BY 1")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.cut_size(net.weights, parts)


@query("cut_size_unit_cost_unpinned", f"""{CTES}, lu AS (SELECT e.layer, e.col, count(DISTINCT p.part) AS lam FROM te e JOIN pt p ON p.layer = e.layer AND p.neuron = e."row" GROUP BY 1, 2) SELECT layer, count(*) FILTER (WHERE lam > 1) AS cut_nets, sum(lam - 1)::BIGINT AS cut FROM lu GROUP BY 1""")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.cut_size(net.weights, parts, 1, pinned=False)


@query("volume_by_layer", f"{CTES} SELECT layer, 2 * count(*) FILTER (WHERE src <> dst) AS words FROM rt GROUP BY 1")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.volume_by_layer(routes.send_map(net.weights, parts))


@query("volume_one_pass_radix", f"{RCTES} SELECT layer, count(*) FILTER (WHERE src <> dst) AS words FROM rt GROUP BY 1")
def _(spark, d):
    net, parts = radix(spark)
    return measures.volume_by_layer(routes.send_map(net.weights, parts), 1)


COST = f"""ms AS (SELECT layer, src, dst, count(*) AS words FROM rt WHERE src <> dst GROUP BY 1, 2, 3), mb AS (SELECT layer, 'fwd' AS pass, src, dst, words FROM ms UNION ALL SELECT layer, 'bwd', dst, src, words FROM ms),
cs AS (SELECT r.range::INTEGER AS part, coalesce((SELECT sum(words) FROM mb WHERE src = r.range), 0)::BIGINT AS sent_words, (SELECT count(*) FROM mb WHERE src = r.range) AS sent_msgs, coalesce((SELECT sum(words) FROM mb WHERE dst = r.range), 0)::BIGINT AS recv_words,
(SELECT count(*) FROM mb WHERE dst = r.range) AS recv_msgs, (SELECT count(*) FROM te e JOIN pt p ON p.layer = e.layer AND p.neuron = e."row" WHERE p.part = r.range) AS load FROM range({P}) r)"""


@query("costs_by_part", f"{CTES}, {COST} SELECT * FROM cs")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.costs(spark, net.weights, parts, routes.send_map(net.weights, parts), P)


@query("volume_sent_avg_max", f"{CTES}, {COST} SELECT round(avg(sent_words), 6) AS avg_words, max(sent_words) AS max_words, round(max(sent_words) / avg(sent_words), 6) AS balance FROM cs")
def _(spark, d):
    net, parts = trade(spark, d)
    c = measures.cost_summary(measures.costs(spark, net.weights, parts, routes.send_map(net.weights, parts), P))
    return c.select(r6("avg_words").alias("avg_words"), "max_words", r6("balance").alias("balance"))


@query("messages_sent_avg_max", f"{CTES}, {COST} SELECT round(avg(sent_msgs), 6) AS avg_msgs, max(sent_msgs) AS max_msgs FROM cs")
def _(spark, d):
    net, parts = trade(spark, d)
    c = measures.cost_summary(measures.costs(spark, net.weights, parts, routes.send_map(net.weights, parts), P))
    return c.select(r6("avg_msgs").alias("avg_msgs"), "max_msgs")


_LOADS = f"""ld AS (SELECT l.layer, r.range AS part, (SELECT count(*) FROM te e JOIN pt p ON p.layer = e.layer AND p.neuron = e."row" WHERE e.layer = l.layer AND p.part = r.range) AS load FROM (SELECT DISTINCT layer FROM te) l, range({P}) r)"""


@query("imbalance_by_layer", f"{CTES}, {_LOADS} SELECT layer, round(max(load) / avg(load), 6) AS imbalance FROM ld GROUP BY 1")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.imbalance_by_layer(net.weights, parts, P).select("layer", r6("imbalance").alias("imbalance"))


@query("imbalance_network", f"{CTES}, {COST} SELECT round(max(load) / avg(load), 6) AS imbalance FROM cs")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.imbalance(net.weights, parts, P).select(r6("imbalance").alias("imbalance"))


@query("imbalance_layer_mean", f"{CTES}, {_LOADS} SELECT round(avg(imb), 6) AS imbalance FROM (SELECT max(load) / avg(load) AS imb FROM ld GROUP BY layer)")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.imbalance(net.weights, parts, P, "layer_mean").select(r6("imbalance").alias("imbalance"))


@query("send_recv_balance", f"{CTES}, {COST} SELECT sum(sent_words)::BIGINT AS sent, sum(recv_words)::BIGINT AS received, count(*) FILTER (WHERE sent_words <> recv_words) AS differing FROM cs")
def _(spark, d):
    net, parts = trade(spark, d)
    c = measures.costs(spark, net.weights, parts, routes.send_map(net.weights, parts), P)
    return c.agg(F.sum("sent_words").alias("sent"), F.sum("recv_words").alias("received"), F.count_if(F.col("sent_words") != F.col("recv_words")).alias("differing"))


@query("internode_volume", f"{CTES} SELECT layer, 2 * count(*) FILTER (WHERE s <> t) AS words FROM (SELECT DISTINCT layer, neuron, src // 2 AS s, dst // 2 AS t FROM rt) GROUP BY 1")
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.internode_volume(routes.send_map(net.weights, parts), 2)


@query("two_level_costs", f"{CTES} SELECT layer, src // 2 AS src, dst // 2 AS dst, count(DISTINCT neuron) AS words FROM rt WHERE src // 2 <> dst // 2 GROUP BY 1, 2, 3")
def _(spark, d):
    net, parts = trade(spark, d)
    r = routes.send_map(net.weights, partition.group_parts(parts, 2))
    return routes.messages(r).select("layer", "src", "dst", "words")


@query(
    "volume_ratio_report",
    f"""{CTES}, {COST}, bl AS (SELECT layer, neuron, (ntile({P}) OVER (PARTITION BY layer ORDER BY neuron) - 1)::INTEGER AS part FROM tn WHERE layer > 0),
bo AS (SELECT col AS neuron, part FROM (SELECT e.col, p.part, row_number() OVER (PARTITION BY e.col ORDER BY count(*) DESC, p.part) AS nth FROM te e JOIN bl p ON p.layer = 1 AND p.neuron = e."row" WHERE e.layer = 1 GROUP BY e.col, p.part) WHERE nth = 1),
bp AS (SELECT * FROM bl UNION ALL SELECT 0, n.neuron, coalesce(bo.part, ({H(0, 'n.neuron', SEED)} % {P})::INTEGER) FROM tn n LEFT JOIN bo USING (neuron) WHERE n.layer = 0),
{routes_sql('te', 'bp', 'br')}, b2 AS (SELECT layer, src, dst, count(*) AS words FROM br WHERE src <> dst GROUP BY 1, 2, 3),
bs AS (SELECT src, sum(words) AS w, sum(m) AS m FROM (SELECT src, words, 1 AS m FROM b2 UNION ALL SELECT dst, words, 1 FROM b2) GROUP BY 1), bz AS (SELECT r.range AS part, coalesce(bs.w, 0) AS w, coalesce(bs.m, 0) AS m FROM range({P}) r LEFT JOIN bs ON bs.src = r.range)
SELECT round(x.aw / y.aw, 6) AS avg_words_ratio, round(x.mw / y.mw, 6) AS max_words_ratio, round(x.am / y.am, 6) AS avg_msgs_ratio, round(x.mm / y.mm, 6) AS max_msgs_ratio
FROM (SELECT avg(w) AS aw, max(w)::DOUBLE AS mw, avg(m) AS am, max(m)::DOUBLE AS mm FROM bz) x, (SELECT avg(sent_words) AS aw, max(sent_words) AS mw, avg(sent_msgs) AS am, max(sent_msgs) AS mm FROM cs) y""",
)
def _(spark, d):
    net, parts = trade(spark, d)
    block = partition.with_inputs(net, partition.block_parts(net.neurons, P), P)
    one = lambda p: measures.cost_summary(measures.costs(spark, net.weights, p, routes.send_map(net.weights, p), P))
    report = measures.ratio_report(one(block), one(parts))
    return report.select(*[r6(c).alias(c) for c in report.columns if c.endswith("_ratio")])


@query("cost_rollup", f"{CTES}, {COST} SELECT coalesce(layer, 0) AS layer, coalesce(pass, 'both') AS pass, sum(words)::BIGINT AS words, count(*) AS msgs FROM mb GROUP BY ROLLUP (layer, pass)")
def _(spark, d):
    net, parts = trade(spark, d)
    m = routes.message_sizes(routes.send_map(net.weights, parts))
    return m.rollup("layer", "pass").agg(F.sum("words").alias("words"), F.count(F.lit(1)).alias("msgs")).na.fill(0, ["layer"]).na.fill("both", ["pass"])


@query("cost_cube_pivot", f"{CTES}, {COST} SELECT layer, sum(words) FILTER (WHERE pass = 'fwd')::BIGINT AS fwd, sum(words) FILTER (WHERE pass = 'bwd')::BIGINT AS bwd FROM mb GROUP BY 1")
def _(spark, d):
    net, parts = trade(spark, d)
    return routes.message_sizes(routes.send_map(net.weights, parts)).groupBy("layer").pivot("pass", ["fwd", "bwd"]).agg(F.sum("words"))


@query("memory_share_by_part", f'{CTES} SELECT p.part, count(*) * 20 AS model_bytes, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM te e JOIN pt p ON p.layer = e.layer AND p.neuron = e."row" GROUP BY 1')
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.memory_share(net.weights, parts).select("part", "model_bytes", r6("share").alias("share"))


PS = [32, 64, 128, 256, 512]
PS_SQL = f"(VALUES {', '.join(f'({p})' for p in PS)}) AS t(p)"


@query("expected_random_volume", f"""WITH {TRADE}, dg AS (SELECT d, count(*) AS n FROM (SELECT layer, col, count(*) AS d FROM te GROUP BY 1, 2) GROUP BY 1)
SELECT p::INTEGER AS parts, round(sum(n * (p - 1) * (1 - (1 - 1.0::DOUBLE / p) ** d) * 2 / p), 3) AS words FROM dg, {PS_SQL} GROUP BY p""")
def _(spark, d):
    return measures.expected_random_words(topology.trade_network(spark, d).weights, PS).select("parts", F.round("words", 3).alias("words"))


@query("dynamic_volume_nonzero", f"{RCTES}, ix AS (SELECT vec_id, i - 1 AS neuron, embedding[i] AS v FROM embeddings, range(1, 65) t(i) WHERE embedding[i] > 0) SELECT 1 AS layer, count(*) AS words FROM rt JOIN ix ON ix.neuron = rt.neuron WHERE rt.layer = 1 AND src <> dst")
def _(spark, d):
    net, parts = radix(spark)
    return measures.dynamic_volume(routes.send_map(net.weights, parts), images(spark, d).withColumn("layer", F.lit(1)))


@query("locality_distinct_inputs", f'{CTES} SELECT layer, count(*) AS inputs FROM (SELECT DISTINCT e.layer, p.part, e.col FROM te e JOIN pt p ON p.layer = e.layer AND p.neuron = e."row") GROUP BY 1')
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.locality(net.weights, parts)


@query("sync_count", "SELECT max(layer)::INTEGER AS forward, 2 * max(layer)::INTEGER - 1 AS both_passes FROM (SELECT unnest([1, 2, 3, 4]) AS layer)")
def _(spark, d):
    """Exchanges in the plans of a step on placed data, counted: one a layer forward, and one a layer but the first backward."""
    net = topology.trade_network(spark, d)
    sh = Sharded.of(net, partition.random_parts(net.neurons, P, SEED), P)
    x = trade_months(spark, d)
    vs = cut_lineage(x.select("vec_id").distinct())
    forward = measures.exchanges(forward_sharded(sh, x, vs)) - measures.exchanges(placed_inputs(sh, x))
    backward = 0
    for k in range(2, net.depth + 1):
        some = cut_placed(sh.weights(k).select("part", "row", "col", F.lit(0).cast("bigint").alias("vec_id"), "w", F.lit(1.0).alias("delta")))
        before = cut_placed(sh.neurons(k - 1).select("part", "neuron", F.lit(0).cast("bigint").alias("vec_id"), F.lit(0.0).alias("z"), F.lit(0.5).alias("x")))
        backward += measures.exchanges(returned_sums(sh, some, before, k))
    return spark.range(1).select(F.lit(forward).alias("forward"), F.lit(forward + backward).alias("both_passes"))


@query("break_even_vectors", f"""WITH {TRADE}, q AS (SELECT unnest([32, 128]) AS p), nd AS (SELECT DISTINCT p, col, ({H('layer', '"row"', SEED)} % p) AS dst FROM te, q WHERE layer = 1),
sv AS (SELECT p, count(DISTINCT col) - count(*) FILTER (WHERE dst = {H(0, 'col', SEED)} % p) AS saved FROM nd GROUP BY 1)
SELECT p::INTEGER AS parts, round(CASE WHEN saved > 0 THEN (SELECT count(*) FROM te WHERE layer = 1)::DOUBLE / saved ELSE 'inf'::DOUBLE END, 3) AS vectors FROM sv""")
def _(spark, d):
    """Vectors after which it has paid to read the first layer's links once and give each input to its most frequent reader, not to a part by hash."""
    net = topology.trade_network(spark, d)
    first = cut_lineage(net.weights.filter("layer = 1").select("row", "col"))
    each = first.select("row", "col", F.explode(F.array(F.lit(32), F.lit(128))).alias("parts"))
    readers = each.select("parts", "col", (portable_hash(1, F.col("row"), SEED) % F.col("parts")).alias("dst")).distinct()
    # an owner that reads its input saves one word of it
    by = readers.groupBy("parts").agg((F.count_distinct("col") - F.count_if(F.col("dst") == portable_hash(0, F.col("col"), SEED) % F.col("parts"))).alias("saved"))
    links = first.agg(F.count(F.lit(1)).alias("links"))
    return by.crossJoin(F.broadcast(links)).select("parts", F.round(measures.break_even_column(F.col("links"), F.col("saved")), 3).alias("vectors"))


@query("ideal_speedup", f"""WITH {TRADE}, ld AS (SELECT {H('layer', '"row"', SEED)} % 32 AS part, count(*) AS n FROM te GROUP BY 1) SELECT p::INTEGER AS parts, round(max(n)::DOUBLE * 32 / p, 1) AS links FROM ld, {PS_SQL} GROUP BY p""")
def _(spark, d):
    """Links that the busiest of 32 random parts works through for a vector, and what they would fall to on more parts."""
    net = topology.trade_network(spark, d)
    busiest = measures.loads(net.weights, partition.random_parts(net.neurons, 32, SEED), 32).groupBy("part").agg(F.sum("load").alias("load")).agg(F.max("load").cast("double").alias("first"))
    each = F.explode(F.array(*[F.struct(F.lit(p).alias("parts"), t.alias("links")) for p, t in zip(PS, measures.ideal_times(F.col("first"), 32, PS), strict=True)])).alias("e")
    return busiest.select(each).select("e.parts", F.round("e.links", 1).alias("links"))


@query("connectivity_bitmask", f'{CTES} SELECT e.layer, e.col AS net, count(DISTINCT p.part)::INTEGER AS lam FROM te e JOIN pt p ON p.layer = e.layer AND p.neuron = e."row" GROUP BY 1, 2')
def _(spark, d):
    net, parts = trade(spark, d)
    return measures.connectivity_mask(net.weights, parts)


@query("connectivity_sketch_merged")
def _(spark, d):
    net, parts = trade(spark, d)
    s = measures.connectivity_sketch(net.weights, parts)
    return s.unionByName(s).groupBy("layer").agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("pairs"))


@query("blocks_round_trip", f'WITH {TRADE} SELECT layer, "row", col, w FROM tw')
def _(spark, d):
    net, parts = trade(spark, d)
    return inference.from_blocks(inference.to_blocks(net.weights, parts))


@query("choose_inference", "SELECT 'replicated' AS small, 'sharded' AS large")
def _(spark, d):
    net = topology.trade_network(spark, d)
    return spark.createDataFrame([(inference.choose_inference(net), inference.choose_inference(net, 1000))], "small string, large string")


@query("duplicate_links", 'SELECT 1 AS layer, 0::BIGINT AS "row", 0::BIGINT AS col, 2::BIGINT AS times')
def _(spark, d):
    from ..sources.tables import duplicate_links

    w = topology.trade_network(spark, d).weights
    again = spark.createDataFrame([(1, 0, 0, 0.5), (1, 0, 0, 0.5)], "layer int, row long, col long, w double")
    return duplicate_links(w.filter("layer = 4").unionByName(again))
