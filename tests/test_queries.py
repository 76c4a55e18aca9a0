"""Each query that SQL can express, against DuckDB on the small tables; bench and entry contracts."""

from __future__ import annotations

import glob
import os

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.01"
FAST = ["points_fold", "points_profile", "points_nested", "dict_time", "points_subset", "planted_points", "planted_five_points", "planted_lineitem_points", "star_join_points", "token_points", "session_points", "cells_fixed", "score_terms_fixed", "score_levels_fixed", "score_null", "score_finest", "ln_partitions_table", "sql_functions", "merge_deltas_seq", "merge_deltas_time", "merge_deltas_event", "move_deltas_event", "boundary_deltas", "typicality_event", "view_cmi", "view_contrast_focus_e", "cube_marginals", "five_marginals", "fit_conversations_seq", "fit_toy32", "unseen_values", "asof_cuts"]


def value(x) -> str:
    if x is None or x is pd.NA or x != x:
        return "null"
    if type(x).__name__ in ("bool", "bool_"):
        return str(bool(x))
    try:
        return repr(float(x))
    except (TypeError, ValueError):
        return str(x)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return con


@pytest.mark.parametrize("name", FAST)
def test_against_sql(spark, duck, name):
    got, want = entry.queries()[name](spark, SF).toPandas(), duck.execute(entry.oracle_sql()[name]).fetchdf()
    columns = sorted(got.columns)
    assert columns == sorted(want.columns)
    rows = lambda d: sorted(tuple(value(x) for x in r) for r in d[columns].itertuples(index=False))
    assert rows(got) == rows(want)


def test_contract(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).count() == 8
