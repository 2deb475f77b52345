"""Queries on streams and experiments."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import partition, topology
from ..plans import blocks, trainer, workloads
from ..session import cut_lineage
from ..streaming import events as S
from .base import SEED, P, forward_sql, query, r6, radix_sql
from .network import IMG_CTES, L8, RN, digits, image_net, images


@query("stream_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, d):
    return S.run_to_table(S.tumbling(S.event_stream(spark, d)), "complete").select(F.col("window.start").alias("start"), "event_type", "n")


@query("stream_sliding", "SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 3 HOUR, ts) - k.range * INTERVAL 3 HOUR AS start FROM events, range(2) k) GROUP BY 1")
def _(spark, d):
    return S.run_to_table(S.sliding(S.event_stream(spark, d)), "complete").select(F.col("window.start").alias("start"), "n")


@query(
    "stream_session",
    "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, session",
)
def _(spark, d):
    return S.run_to_table(S.sessions(S.event_stream(spark, d)), "complete").select("user_id", F.col("session_window.start").alias("start"), "n")


@query("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    e = S.event_stream(spark, d)
    return S.run_to_table(S.deduplicated(e.unionByName(S.event_stream(spark, d))).select("event_type"), "append").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("stream_interval_join", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 6 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def _(spark, d):
    return S.run_to_table(S.clicks_to_purchases(S.event_stream(spark, d)), "append")


@query("stream_user_recency", "SELECT user_id, count(*) AS events, max(epoch(ts)::BIGINT) AS last_at FROM (SELECT user_id, date_trunc('second', ts) AS ts FROM events) GROUP BY 1")
def _(spark, d):
    return S.run_to_table(S.user_recency(S.event_stream(spark, d)), "update")


EV = f"""WITH {radix_sql(128, 2, 8)}, {RN(128, 2)}, ex AS (SELECT DISTINCT user_id * 1000 + date_diff('day', DATE '2024-01-01', ts::DATE) AS vec_id, ((list_position(['signup', 'view', 'purchase', 'error', 'click'], event_type) - 1) * 24 + hour(ts))::BIGINT AS neuron, 1.0::DOUBLE AS x
FROM events WHERE event_type IN ('signup', 'view', 'purchase', 'error', 'click')), {forward_sql('rw', 'rn', 'ex', 2, 'relu')}"""


@query("stream_inference", f"{EV} SELECT neuron, sum(x) AS x FROM a2 WHERE x <> 0 GROUP BY 1")
def _(spark, d):
    net = topology.radix_network(spark, 128, 2, 8, "relu")
    return S.stream_inference(S.event_stream(spark, d), net).filter("x <> 0").groupBy("neuron").agg(F.sum("x").alias("x"))


@query("workload_communication")
def _(spark, d):
    return workloads.communication_table(spark, (256, 1024), (4, 16), layers=6)


@query("workload_random_row_matches", "SELECT p::INTEGER AS parts, true AS words_match, true AS messages_match, true AS imbalance_match FROM (VALUES (32), (64), (128)) AS t(p)")
def _(spark, d):
    """Random placement of 1,024 neurons, 120 layers and 32 inputs against the published figures, within 5 % (messages in whole thousands)."""
    published = {32: (149, 7, 1.05), 64: (94, 15, 1.05), 128: (53, 24, 1.08)}
    rows = []
    for p, (words, msgs, imb) in published.items():
        r = workloads.random_row(1024, 32, 120, p)
        rows.append((p, bool(abs(r["avg_words"] / words - 1) < 0.05), bool(abs(r["avg_msgs"] - msgs) < 0.6), bool(abs(r["imbalance"] / imb - 1) < 0.05)))
    return spark.createDataFrame(rows, "parts int, words_match boolean, messages_match boolean, imbalance_match boolean")


@query("workload_inference")
def _(spark, d):
    return workloads.inference_table(spark, d)


@query("workload_partition_times")
def _(spark, d):
    return workloads.partition_grid(spark)


@query("workload_partition_trends", """SELECT n AS neurons, k AS layers, p, n * k AS placed, true AS balanced, true AS halved, true AS grows_with_p, true AS grows_with_layers
FROM (VALUES (256), (1024)) AS a(n), (VALUES (2), (6)) AS b(k), (VALUES (4), (8), (16)) AS c(p)""")
def _(spark, d):
    """Each partitioning places every row once and within the capacity, at under half of random placement's words; words grow with parts and layers."""
    t = cut_lineage(workloads.partition_grid(spark))
    more = Window.partitionBy("neurons", "layers").orderBy("p")
    deep = Window.partitionBy("neurons", "p").orderBy("layers")
    grows = lambda w: F.coalesce(F.col("cut") >= F.lag("cut").over(w), F.lit(True))
    return t.select("neurons", "layers", "p", "placed", (F.col("heaviest") <= F.col("capacity")).alias("balanced"), (F.col("ratio") < 0.5).alias("halved"), grows(more).alias("grows_with_p"), grows(deep).alias("grows_with_layers"))


@query("workload_cut_aware_rows", "SELECT p::INTEGER AS p, placed::BIGINT AS placed, true AS balanced, true AS below_published FROM (VALUES (32, 12288), (64, 12288), (128, 12288)) AS t(p, placed)")
def _(spark, d):
    """1,024 neurons, 32 inputs, 12 layers on 32 to 128 parts: words as a share of random placement's, against the published shares."""
    t = workloads.partition_grid(spark, (1024,), (32, 64, 128), (12,), 32)
    published = F.element_at(F.create_map(*[F.lit(v) for pair in ((32, 0.34), (64, 0.31), (128, 0.29)) for v in pair]), F.col("p"))
    return t.select("p", "placed", (F.col("heaviest") <= F.col("capacity")).alias("balanced"), (F.col("ratio") <= published).alias("below_published"))


@query("train_sharded_batches")
def _(spark, d):
    net = image_net(spark, "sigmoid")
    return blocks.train_blocks(net, images(spark, d), digits(spark, d), partition.random_parts(net.neurons, P, SEED), P, trainer.RunConfig(eta=0.5, batch=10_000)).weights


@query("train_replicated_batch")
def _(spark, d):
    return trainer.train_replicated(image_net(spark, "sigmoid"), images(spark, d), digits(spark, d), trainer.RunConfig(eta=0.5, batch=10_000)).weights


@query("prune_and_retrain")
def _(spark, d):
    net = image_net(spark, "sigmoid")
    net = net.with_weights(topology.prune(net.weights, 0.5))
    return trainer.train_replicated(net, images(spark, d), digits(spark, d), trainer.RunConfig(eta=0.5, batch=10_000)).weights


