"""A query of each kind against its DuckDB oracle, and the entry points."""

import os

import duckdb
import pytest

import __spark_entry__ as entry

SOME = ["encode_trade_months", "trade_network_edges", "forward_trade_relu", "update_one_step", "random_partition_balanced", "move_gains_one_round", "messages_by_pair", "cut_size_by_layer", "costs_by_part", "join_asof", "join_range", "agg_cube", "window_lag_lead", "map_ops", "sql_functions", "data_source_radix", "stream_sliding"]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for f in os.listdir(sf):
        con.sql(f"create view {f.split('.')[0]} as select * from read_parquet('{sf}/{f}')")
    return con


def rows(df):
    df = df[sorted(df.columns)]
    return sorted(tuple(round(v, 7) + 0.0 if isinstance(v, float) else str(v) for v in r) for r in df.itertuples(index=False))


@pytest.mark.parametrize("name", SOME)
def test_query(spark, sf, duck, name):
    assert rows(entry.queries()[name](spark, sf).toPandas()) == rows(duck.sql(entry.oracle_sql()[name]).df())


@pytest.mark.parametrize("name", ["avgpool_layer_edges", "break_even_vectors", "conv_layer_edges", "data_source_radix", "expected_random_volume", "ideal_speedup"])
def test_query_of_a_table(spark, sf, duck, name):
    """The result comes from the given table: it equals the oracle's there and differs on another table."""
    got = rows(entry.queries()[name](spark, sf).toPandas())
    assert got == rows(duck.sql(entry.oracle_sql()[name]).df())
    assert got != rows(entry.queries()[name](spark, "/root/testdata/sf0.01").toPandas())


@pytest.mark.parametrize("name", ["cut_aware_beats_random", "cut_aware_partition", "distributed_refinement", "greedy_input_affinity_partition"])
def test_parts_of_hours(spark, duck, name):
    """The rows placed are the hours of the given events, or the comparison over them is the oracle's."""
    sf = "/root/testdata/sf0.01"
    got = entry.queries()[name](spark, sf).toPandas()
    if name in entry.oracle_sql():
        assert rows(got) == rows(duck.sql(entry.oracle_sql()[name]).df())
        return
    hours = {r[0] for r in duck.sql(f"select distinct epoch(ts)::bigint // 3600 from (select date_trunc('hour', ts) as ts from '{sf}/events.parquet')").fetchall()}
    assert set(got["neuron"]) == hours and got["part"].between(0, 3).all()
    assert not got.duplicated([c for c in ("layer", "neuron") if c in got]).any()


def test_entry(spark):
    out = entry.entry(spark)
    assert out.count() > 0 and out.columns == ["vec_id", "region", "x", "words_per_vector"]


def test_oracles_have_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())
