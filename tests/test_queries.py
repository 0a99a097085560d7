"""Queries beside their SQL on the smallest tables, and the entry module."""

import itertools

import duckdb
import pytest

import __spark_entry__
from fewbit.plans.methods import METHODS
from fewbit.queries import oracles, queries
from fewbit.queries.methods import NAMES, ROUNDS

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = [
    "m07_adaptive_plus", "b06_quantized_sag", "m02_avr_memory", "m17_geometry", "task_charge", "task_language_cells", "w02_epoch_by_bits", "c05_w13_ledger", "m09_random_rounding",
    "flagship_adaptive_plus", "m07_adaptive_plus_sharded_store", "m20_least_squares", "c15_pass_costs", "op_sql_views", "c06_bits_rollup", "c06_message_sizes", "c08_c11_c13_curves", "c03_c04_f1_of_given_models",
    "h01_h08_bounds", "h09_h13_targets", "h11_h12_step_windows", "c07_w08_compression", "c14_w14_rounding_bias", "task_language", "task_quality", "task_sensor", "op_join_interval", "op_range_join_cells",
    "src_formats", "src_run_store", "st_late_rows", "st_append", "st_static_join", "st_training", "op_sql_functions", "op_join_asof", "op_join_semi_anti", "op_window_range", "op_set_operations", "op_agg_cube", "st_windows", "st_worker_state",
]


def shown(rows, names):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(tuple(str(r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("name", SOME)
def test_same_rows_as_sql(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = queries()[name](spark, sf)
    rel = con.execute(oracles()[name])
    names = [c[0] for c in rel.description]
    assert sorted(df.columns) == sorted(names)
    assert shown(df.collect(), df.columns) == shown(rel.fetchall(), names)


#: Queries that once made up their data: each reads a given table now.
READ = [
    "c05_w13_ledger",
    "c07_w08_compression",
    "c14_w14_rounding_bias",
    "h01_h08_bounds",
    "h09_h13_targets",
    "h11_h12_step_windows",
    "m11_lattice_points",
    "m14_draws",
    "op_bounds_table_function",
    "op_table_function",
    "w01_epoch_by_step",
    "w02_epoch_by_bits",
]


@pytest.mark.parametrize("name", READ)
def test_reads_a_given_table(spark, sf, name):
    assert queries()[name](spark, sf).inputFiles()
    test_same_rows_as_sql(spark, sf, name)


def test_method_queries_tell_the_methods_apart(spark, sf):
    """No two methods give the same rows; the loss falls where nothing is in the way; the memory acts in some run of each that has one."""
    rows = {m: {(r.setting, r.k): (r.loss, r.grad_norm, r.accepted) for r in queries()[NAMES[m]](spark, sf).collect()} for m in METHODS}
    assert not [(a, b) for a, b in itertools.combinations(METHODS, 2) if rows[a] == rows[b]]
    for m, spec in METHODS.items():
        loss = [rows[m]["nine_bits", k][0] for k in range(1, ROUNDS + 2)]
        assert loss[-1] < loss[0] - 0.01 and len(set(loss)) == len(loss), m
        assert any(not accepted for _, _, accepted in rows[m].values()) == spec.memory, m


def test_oracles_belong_to_queries():
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_entry(spark):
    out = __spark_entry__.entry(spark)
    assert out.count() == 11
