"""Late rows, timers, listeners, online training, and what readers and writers keep."""

import datetime as dt
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from layercut.operators import cut_aware, measures, partition, passes, topology
from layercut.session import cut_lineage
from layercut.sources import tables
from layercut.sources.versions import complete_steps, load_step, save_step
from layercut.streaming import events as S

DAY = dt.datetime(2024, 1, 3)


def write_events(spark, folder, batches):
    """One file a batch, read in this order; batch: (event_id, hours after DAY, user_id, event_type)."""
    for k, rows in enumerate(batches):
        made = [(i, DAY + dt.timedelta(hours=h), u, kind, 0.0, "{}") for i, h, u, kind in rows]
        spark.createDataFrame(made, S.EVENTS).coalesce(1).write.parquet(f"{folder}/part{k}")
        time.sleep(0.05)
    return S.event_stream(spark, f"{folder}/*", "*.parquet")


@pytest.fixture
def late_batches():
    return [[(1, 0, 1, "click"), (2, 30, 1, "click")], [(3, 40, 2, "view")], [(4, 2, 1, "click"), (5, 41, 2, "click")]]


def test_late_rows_are_dropped(spark, tmp_path, late_batches):
    """Row 4 lies more than the lateness behind the watermark of the batches before it."""
    seen = S.Progress()
    spark.streams.addListener(seen)
    try:
        got = S.run_to_table(S.tumbling(write_events(spark, tmp_path, late_batches)), "append")
        counted = {(r["start"], r["event_type"]): r["n"] for r in got.select(F.col("window.start").alias("start"), "event_type", "n").collect()}
        assert counted == {(DAY, "click"): 1}  # day 1 is closed with one click; later days are still open
        until = time.time() + 20
        while time.time() < until and sum(seen.late.values()) < 1:
            time.sleep(0.2)
    finally:
        spark.streams.removeListener(seen)
    assert sum(seen.late.values()) == 1 and sum(seen.read.values()) == 5 and max(seen.batches.values()) >= 3


def test_idle_users_time_out(spark, tmp_path, late_batches):
    got = S.run_to_table(S.idle_users(write_events(spark, tmp_path, late_batches)), "append").collect()
    first = {r["user_id"]: r["events"] for r in got}
    assert first == {1: 2}  # user 1 is idle from hour 30 on, user 2 still active at the end; row 4 came too late


def test_deduplication_across_batches(spark, tmp_path):
    stream = write_events(spark, tmp_path, [[(1, 1, 1, "click"), (1, 1, 1, "click")], [(1, 1, 1, "click"), (2, 2, 1, "view")]])
    assert sorted(r["event_id"] for r in S.run_to_table(S.deduplicated(stream), "append").collect()) == [1, 2]


def test_online_training_equals_batches(spark, tmp_path):
    net = topology.radix_network(spark, 128, 2, 8)
    rows = [[(k, h, 1 + k % 2, kind) for k, (h, kind) in enumerate([(1, "click"), (2, "view"), (3, "purchase")])], [(9, 30, 3, "signup"), (10, 31, 3, "error")]]
    targets = lambda x: x.select("vec_id").distinct().withColumn("neuron", F.lit(0).cast("long")).withColumn("y", F.lit(1.0))
    stream = write_events(spark, tmp_path / "in", rows)
    got = S.online_train(stream, net, targets, str(tmp_path / "steps"), 0.1)
    want = net
    for k in range(2):
        x = S.window_vectors(spark.read.parquet(str(tmp_path / "in" / f"part{k}")))
        want = passes.step(want, x, targets(x), 0.1, x.select("vec_id").distinct().count())
    a, b = ({(r["layer"], r["row"], r["col"]): r["w"] for r in n.weights.collect()} for n in (got, want))
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-12 for k in a) and complete_steps(spark, str(tmp_path / "steps")) == [1, 2]


def test_tables_round_trip(spark, tmp_path):
    net = topology.radix_network(spark, 64, 3, 4)
    rows = sorted(tuple(r) for r in net.weights.select("layer", "row", "col", "w").collect())
    tables.write_weights(net.weights, str(tmp_path / "w"))
    assert sorted(tuple(r) for r in tables.read_layer(spark, str(tmp_path / "w")).collect()) == rows
    one = tables.read_layer(spark, str(tmp_path / "w"), 2)
    assert one.count() == 64 * 4 and "PartitionFilters: [isnotnull(layer" in one._jdf.queryExecution().executedPlan().toString()
    placed = net.weights.withColumn("part", (F.col("row") % 3).cast("int"))
    tables.write_blocks(placed, str(tmp_path / "b"))
    assert tables.read_block(spark, str(tmp_path / "b"), 1, 2).count() == placed.filter("layer = 1 and part = 2").count()
    tables.write_edges(net.layer(1), str(tmp_path / "e"))
    (tmp_path / "e" / "odd.csv").write_text("1\tx\t2\n")
    back = tables.read_edges(spark, str(tmp_path / "e")).cache()
    assert back.filter("bad is null").count() == 64 * 4 and back.filter("bad is not null").count() == 1
    (tmp_path / "j.json").write_text('{"vec_id": 1, "neuron": 2, "x": 0.5}\n{"vec_id": 2}\n')
    assert [tuple(r) for r in tables.read_json_lines(spark, str(tmp_path / "j.json"), tables.INPUTS).orderBy("vec_id").collect()] == [(1, 2, 0.5), (2, None, None)]
    tables.write_any(net.weights, None, "noop")
    tables.write_any(net.weights, str(tmp_path / "o"), "orc")
    assert spark.read.orc(str(tmp_path / "o")).count() == len(rows)


def test_checks_of_weights(spark):
    good = spark.createDataFrame([(1, 1, 1, 0.5), (1, 1, 1, 0.25)], tables.WEIGHTS)
    assert tables.check_weights(good).count() == 2 and tables.duplicate_links(good).first()["times"] == 2
    with pytest.raises(Exception, match="null or NaN weight"):
        tables.check_weights(spark.createDataFrame([(1, 1, 1, float("nan"))], tables.WEIGHTS)).collect()


def test_versions(spark, tmp_path):
    root, w = str(tmp_path / "v"), topology.radix_network(spark, 16, 1, 2).weights
    assert complete_steps(spark, root) == []
    with pytest.raises(FileNotFoundError):
        load_step(spark, root)
    for k in (1, 2):
        save_step(w, root, k)
    (tmp_path / "v" / "step=3").mkdir()  # a step that was cut off has no mark
    assert complete_steps(spark, root) == [1, 2] and load_step(spark, root)[0] == 2


def test_unequal_shares(spark):
    """Shares (2, 1, 1): loads stay within each part's own capacity, and the cut below that of random parts."""
    net = topology.radix_network(spark, 128, 3, 8, seed=5)
    parts = cut_aware.cut_aware_parts(net, 3, eps=0.05, shares=[2, 1, 1])
    loads = {(r["layer"], r["part"]): r["load"] for r in measures.loads(net.weights, parts, 3).collect()}
    room = {(r["layer"], r["part"]): r["capacity"] for r in partition.capacities(net.weights, 3, 0.05, [2, 1, 1]).collect()}
    assert all(loads[k] <= room[k] for k in loads) and all(loads[(k, 0)] > 1.5 * loads[(k, 1)] for k in (1, 2, 3))
    full = lambda p: partition.with_inputs(net, p, 3)
    assert cut_aware.total_cut(net, full(parts)) < cut_aware.total_cut(net, full(partition.random_parts(net.neurons, 3)))


def test_pinned_inputs_pay(spark):
    """The ablation: layers partitioned without the owners of their inputs end with more words between parts."""
    net = topology.radix_network(spark, 256, 4, 16, seed=5)
    made = {pin: partition.with_inputs(net, cut_aware.multilevel_parts(net, 4, trials=1, pin_inputs=pin), 4) for pin in (True, False)}
    assert cut_aware.total_cut(net, made[True]) < 0.95 * cut_aware.total_cut(net, made[False])


def test_distributed_rounds_against_one_task(spark):
    """Both partitioners on one network: below random parts, loads within the capacities."""
    net = topology.radix_network(spark, 64, 2, 8, seed=5)
    many = cut_lineage(cut_aware.distributed_parts(net, 4, 0.1, rounds=2))
    cut = lambda p: cut_aware.total_cut(net, partition.with_inputs(net, p, 4))
    random = cut(partition.random_parts(net.neurons, 4, balanced=True))
    assert cut(cut_aware.multilevel_parts(net, 4, 0.1, trials=1)) < random and cut(many) < random
    loads = measures.loads(net.weights, many, 4).toPandas()
    assert (loads["load"] <= np.floor(64 * 8 / 4 * 1.1) + 8).all()
