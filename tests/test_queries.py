"""Registered queries against their SQL in DuckDB on the smallest tables."""

import os

import duckdb
import pandas as pd
import pytest

from arcloom import queries as registry

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = "build_copart build_words build_docline scan_pruned k1_sssp_copart k1_bfs_levels k1_within k2_strength k2_power_10 k1_path_tree_zero k1_paths k1_sources k3_coalesce_once k3_batch_round k3_batch_contract k3_hierarchy_map k3_edge_map k3_redirect k3_squares k4_bc_exact grid_metric k5_move_gains repr_bfs_layouts growth_userseq fn_tokens stream_state stream_updates stream_late k4_cc_all k4_modularity k5_density k5_objective_cells gen_pointer_edges repr_equivalence measure_footprint base_extreme_edges join_slot_range join_asof_events agg_rollup_geo win_range_value set_except_edges fn_csr_slice udtf_csr_expand io_csv_roundtrip stream_session".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        p = f"{DIR}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{p}{'/*.parquet' if os.path.isdir(p) else ''}'")
    return con


def rows(df: pd.DataFrame):
    cols = sorted(df.columns)
    return cols, sorted(tuple("" if pd.isna(v) else repr(float(v)) if isinstance(v, float) else str(v) for v in r) for r in df[cols].astype(object).itertuples(index=False))


def test_every_oracle_has_a_query():
    assert set(registry.oracle_sql()) <= set(registry.queries())


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_sql(spark, duck, name):
    assert rows(registry.queries()[name](spark, DIR).toPandas()) == rows(duck.execute(registry.oracle_sql()[name]).df())
