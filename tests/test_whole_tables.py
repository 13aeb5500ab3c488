"""The operator, chain and merge queries also run over every stake, not only over the dearest."""

import pytest
from oracle_check import connect

from temporal_rules.workloads import oracle, queries

NAMES = [n for n in queries.QUERIES if n.startswith(("op_", "chain_")) and not n.endswith("_all")] + ["coalesce_gap", "merge_hotkey", "merge_streaming", "lift_month", "covered_time"]


@pytest.mark.parametrize("name", NAMES)
def test_is_registered_over_all_stakes(name):
    assert f"{name}_all" in queries.QUERIES and "94700" not in oracle.SQL[f"{name}_all"]


def test_every_pair_reaches_the_operators(spark, sf):
    want = connect(sf).execute("select count(*) from (select distinct o_custkey, l_suppkey from lineitem join orders on l_orderkey = o_orderkey where l_quantity >= 1)").fetchone()[0]
    for name in ("covered_time_all", "op_shift_all"):
        assert queries.QUERIES[name](spark, sf).select("cust", "supp").distinct().count() == want
