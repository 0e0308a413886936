"""Queries about costs and choices take their figures from the given tables: other rows give other figures."""

import os

import pytest


@pytest.mark.parametrize("key, name, half", [("cost_model", "events", "event_id % 3 = 0"), ("hybrid_threshold", "events", "event_id % 3 = 0"), ("select_dp", "part", "p_partkey % 3 = 0"), ("select_exact", "part", "p_partkey % 3 = 0"), ("select_greedy", "part", "p_partkey % 3 = 0"), ("gaps_choose_exact", "customer", "c_nationkey IN (3, 4, 5)")])
def test_figures_come_from_a_table(spark, tiny, tmp_path, key, name, half):
    import __spark_entry__

    for f in os.listdir(tiny):
        if f != f"{name}.parquet":
            os.symlink(f"{tiny}/{f}", tmp_path / f)
    spark.read.parquet(f"{tiny}/{name}.parquet").where(half).write.parquet(str(tmp_path / f"{name}.parquet"))
    run = __spark_entry__.queries()[key]
    whole, part = (sorted(map(tuple, run(spark, d).collect())) for d in (tiny, str(tmp_path)))
    assert whole and whole != part
