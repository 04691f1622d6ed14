"""Queries that once made their data up: each result follows from a given table, as its SQL twin says."""

from __future__ import annotations

import __spark_entry__ as contract
import pytest

NAMES = ["a9_bias_example", "b10_t_matrix", "b6_sizes_100_7", "c4_uniform_replicas", "c6_decode_cost", "k12_trials_needed", "k15_dims", "n7_replicas_lcm", "n8_is_perfect", "r_data_source", "s8_uniform", "u_draw_udtf"]


@pytest.mark.parametrize("name", NAMES)
def test_result_follows_from_a_given_table(spark, sf_dir, name):
    duckdb = pytest.importorskip("duckdb")
    con, sql = duckdb.connect(), contract.oracle_sql()[name]
    read = [t for t in ("customer", "orders", "events") if f"FROM {t}" in sql]
    assert read
    for t in read:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    cursor = con.execute(sql)
    columns = [c[0] for c in cursor.description]
    out = contract.queries()[name](spark, sf_dir)
    assert sorted(out.columns) == sorted(columns)
    assert sorted(map(str, (tuple(r) for r in out.select(*columns).collect()))) == sorted(map(str, cursor.fetchall()))
