"""A part of the registered queries against DuckDB on the smallest tables (all of them with ORDSUM_ALL=1)."""

import os

import pytest

from ordsum.workloads import ALL
from tests.harness import DATA, compare, views

SOME = """op_find op_insert op_delete op_split_mid op_link op_union_noncomm op_union_small op_intersect op_difference op_build_first
op_build_fold op_map_reduce_ordered op_find_many op_neighbor_many op_rank_many op_range_many sum_left_strict sum_range_open sum_filter_max
sum_filter_all sum_project_size sum_range_many_prefix sum_range_many_canonical sum_range_many_overlap bal_priority iv_stab_many iv_report
iv_count_many iv_overlap rect_sum_many rect_max_many rect_sum_dominance rect_list_many idx_and_top10 idx_or_top10 idx_batch_top10
src_store_insert st_ingest udaf_ordered udtf_cover join_asof_tolerance win_range_frame""".split()


@pytest.fixture(scope="module")
def con():
    return views(DATA)


@pytest.mark.parametrize("name", sorted(n for n, (_, s) in ALL.items() if s) if os.environ.get("ORDSUM_ALL") else SOME)
def test_query(spark, con, name):
    f, sql = ALL[name]
    assert compare(spark, name, f, sql, DATA, con) == ""
