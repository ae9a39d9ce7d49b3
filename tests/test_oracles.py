"""Queries against their SQL twins at the smallest scale; the driver runs all of them at a larger one."""

import os
from glob import glob

import duckdb
import pytest

from bitsort.plans import workloads
from tests.conftest import SF

NAMES = [
    "size_line4_sorted_w32", "size_line4_shuffled_w64", "size_event4_sorted_w16", "size_line4_sorted_hybrid31", "block_sort_5", "words_per_column_ascending", "characteristics_rating4", "histogram_line4", "dictionary_frequency_ranks",
    "minimal_bitmaps", "component_encoding", "equi_width_bins", "column_changes", "data_examined_line4", "payload_marker32", "payload_marker64", "eq_count_k2", "eq_count_k4_freq", "range_count_4d_w64", "xnor_count", "predicate_tree_count",
    "symmetric_exactly", "row_ids_answer", "counts_by_value", "combine_or_heap", "combine_or_in_place", "range_join_bins", "as_of_join_events", "saving_curve",
    "size_gram4_shuffled_w32", "typed_double_range", "typed_date_rows", "append_unseen_values", "code_changes", "sorted_bounds", "values_per_bitmap", "equality_sample_counts", "range_sample_counts", "symmetric_all_equal",
]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf, duck, name):
    df = workloads.queries()[name](spark, sf)
    cols = sorted(df.columns)
    flat = lambda x: round(x, 6) if isinstance(x, float) else x
    got = sorted((tuple(flat(r[c]) for c in cols) for r in df.collect()), key=repr)
    answer = duck.execute(workloads.oracle_sql()[name])
    names = [d[0] for d in answer.description]
    want = sorted((tuple(flat(row[names.index(c)]) for c in cols) for row in answer.fetchall()), key=repr)
    assert sorted(names) == cols and got == want
