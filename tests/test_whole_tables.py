from collections import Counter
from itertools import combinations

import pytest

from allpairs import catalog

SF = "/root/testdata/sf0.001"


def test_table_function_pairs_all_parts(spark):
    suppliers = {}
    for r in spark.read.parquet(f"{SF}/lineitem.parquet").select("l_suppkey", "l_partkey").distinct().collect():
        suppliers.setdefault(r["l_partkey"], []).append(r["l_suppkey"])
    want = Counter(p for ids in suppliers.values() for p in combinations(sorted(ids), 2))
    got = {(r["e1"], r["e2"]): r["shared"] for r in catalog.queries()["op_udtf_pairs"](spark, SF).collect()}
    assert got == want


@pytest.mark.parametrize("how,unmatched", [("left", [(None, 5)]), ("right", [(9, None)]), ("full_outer", [(None, 5), (9, None)])])
def test_outer_joins_take_all_orders(spark, tmp_path, how, unmatched):
    spark.createDataFrame([(k, 7) for k in (1, 2, 3, 4, 6)] + [(5, 8)], "o_orderkey long, o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame([(7, 0), (9, 0)], "c_custkey long, c_nationkey int").write.parquet(f"{tmp_path}/customer.parquet")
    got = [(r["c_custkey"], r["o_orderkey"]) for r in catalog.queries()[f"op_join_{how}"](spark, str(tmp_path)).collect()]
    assert sorted(got, key=repr) == sorted([(7, k) for k in (1, 2, 3, 4, 6)] + unmatched, key=repr)
