"""Queries on codes and on the bad family take their numbers from the given tables."""

import pytest

from bitparse import workloads
from bitparse.workloads import tables

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["bad_family", "bad_family_closed_forms", "bad_family_near_copy_parse", "bad_family_shape", "block_work", "code_lengths", "code_log_ratio", "code_monotone", "code_plateaus", "code_q_counts"])
def test_the_rows_follow_the_table(spark, tmp_path, name):
    query = workloads.QUERIES[name]
    whole = query(spark, SMALL).collect()
    lines = tables.read(spark, SMALL, "lineitem")
    lines.filter("l_suppkey % 5 = 0 and l_shipdate < '1995-04-01' and l_tax < 0.05 and l_partkey < 100").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    part = query(spark, str(tmp_path)).collect()
    assert any(f.endswith("lineitem.parquet") for f in query(spark, SMALL).inputFiles())
    assert part and (set(part) != set(whole) or name == "code_monotone")  # which is true of every code either way
    if name in ("bad_family", "bad_family_closed_forms", "code_lengths"):
        assert len(part) < len(whole)


def test_phrases_of_the_family_are_not_made_for_every_line(spark):
    plan = workloads.QUERIES["bad_family_near_copy_parse"](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
    assert "l_tax" in plan and "size(" not in plan
