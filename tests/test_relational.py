"""Relational operators on hand-made tables."""

import pytest

from pairbundle.operators import relational


@pytest.mark.parametrize(("keys", "want"), [([0, 1, 2, 3, 5, 8, 9], [(1, 1), (2, 2), (3, 2), (4, 2)]), ([0], [(1, 1)]), ([14, 15], [(4, 1), (5, 1)]), ([2**63 - 1], [(64, 1)]), ([], [])])
def test_levels_of_the_tree_of_orders(spark, duck, tmp_path, keys, want):
    spark.createDataFrame([(k,) for k in keys], "o_orderkey long").write.parquet(f"{tmp_path}/orders.parquet")
    assert sorted(map(tuple, relational.cte_recursive(spark, str(tmp_path)).collect())) == want
    sql = relational.ORACLES["op_cte_recursive"].replace("orders", f"'{tmp_path}/orders.parquet/*.parquet'")
    assert sorted(duck.execute(sql).fetchall()) == want
