"""Every query with SQL against DuckDB, and what the others must hold."""

import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).parents[1]))
import oracle  # noqa: E402

from bitparse import workloads  # noqa: E402

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    return oracle.connect(SMALL)


@pytest.mark.parametrize("name", sorted(workloads.ORACLE_SQL))
def test_same_as_sql(spark, con, name):
    assert not oracle.compare(spark, con, name, SMALL, workloads.QUERIES[name], workloads.ORACLE_SQL[name])


@pytest.mark.parametrize("name", sorted(set(workloads.QUERIES) - set(workloads.ORACLE_SQL)))
def test_runs(spark, name):
    df = workloads.QUERIES[name](spark, SMALL)
    assert df.count() > 0 and len(set(df.columns)) == len(df.columns)


def test_behaviour(spark):
    """Who wins, and how measures move."""
    import pyspark.sql.functions as F

    docs = {n: {r.seq_id: r for r in workloads.QUERIES[n](spark, SMALL).collect()} for n in ("optimal_bits_gamma", "greedy_documents", "lazy_documents", "length_only_documents", "ratio_greedy_documents", "windowed_optimal_documents", "fewest_documents")}
    for key, best in docs["optimal_bits_gamma"].items():
        assert all(best.bits <= other[key].bits for other in docs.values())
        assert docs["fewest_documents"][key].phrases == docs["greedy_documents"][key].phrases <= best.phrases
    family = workloads.QUERIES["bad_family"](spark, SMALL).orderBy("seq_id").collect()
    assert [(r.greedy, r.optimal) for r in family if r.seq_id in (2, 4, 6, 8, 9)] == [(48, 44), (88, 72), (146, 98), (224, 128), (268, 144)]
    assert all(r.greedy == r.greedy_bits and r.optimal <= r.near_bits <= r.greedy for r in family if r.seq_id >= 4)
    assert all(a.ratio < b.ratio for a, b in zip(family[2:], family[3:], strict=False))
    assert workloads.QUERIES["chunk_seam_penalty"](spark, SMALL).filter(~F.col("within") | (F.col("bits") < F.col("whole"))).count() == 0
    assert workloads.QUERIES["gap_ratio_documents"](spark, SMALL).filter(~F.col("within") | (F.col("ratio") < 1)).count() == 0
