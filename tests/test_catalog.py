"""Registered queries against their SQL on the smallest tables."""

import glob
import os

import duckdb
import pytest
from pyspark.errors import AnalysisException

import __spark_entry__ as entry_module

SF = "/root/testdata/sf0.001"
SOME = ["encode_orders", "encode_lineitem", "u3_high_orders", "cx_high_target", "exchange_slice", "remap_fused", "qft_blocked", "qv_rows_blocked", "batch_orders_circuits", "placement_with_buffers", "sample_shots_two_level", "worked_example_plan", "stream_register_fold", "udtf_qft_gates", "noise_trajectories", "rewriter_variants", "chooser_comparison", "swap_budget", "block_stats_qft", "block_stats_events", "exchange_cost_events", "strong_scaling_model", "tier_traffic", "outcome_ranks", "single_node_sweep", "w_state", "stream_foreachbatch_state", "stream_dead_letters", "front_layer_gates", "approx_distinct_parts", "volume_source_gates"]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        c.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return c


@pytest.mark.parametrize("name", SOME)
def test_matches_sql(spark, con, name):
    got = entry_module.queries()[name](spark, SF)
    want = con.execute(entry_module.oracle_sql()[name])
    names = sorted(x[0] for x in want.description)
    assert sorted(got.columns) == names
    rows = con.execute(f"SELECT {', '.join(names)} FROM ({entry_module.oracle_sql()[name]})").fetchall()
    assert sorted(map(tuple, got.select(*names).collect())) == sorted(rows)


def test_entry(spark):
    rows = entry_module.entry(spark).collect()
    assert len(rows) == 20 and rows[0]["p"] >= rows[-1]["p"]


#: Queries whose job runs over a given table: none has a result without it.
READ = ["amplitude_polar", "basis_encode_nation", "basis_state", "bernstein_vazirani", "bit_ops_states", "bitstring_labels", "block_has_no_exchange", "block_stats_qft", "block_stats_qv", "buffer_overhead", "byte_per_flop", "capacity_table"]


@pytest.mark.parametrize("name", READ)
def test_reads_its_table(spark, con, name, tmp_path):
    with pytest.raises(AnalysisException):
        entry_module.queries()[name](spark, str(tmp_path)).collect()
    test_matches_sql(spark, con, name)
