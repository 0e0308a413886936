"""The indexing curves lay out what they index, build what they report and nothing else, each value scanned once a pass."""

import os

from pyspark.sql import functions as F

from sift import queries_measures as Q
from sift import workloads as W
from sift.operators import build
from sift.operators.kinds import Hybrid


def test_nothing_is_built_beside_the_curves(spark, tiny, tmp_path, monkeypatch):
    for f in os.listdir(tiny):
        os.symlink(f"{tiny}/{f}", tmp_path / f)
    built, inner = [], build.build_summaries

    def noted(spark, source, kinds, store, **how):
        built.append((source, [k.index for k in kinds]))
        return inner(spark, source, kinds, store, **how)

    monkeypatch.setattr(build, "build_summaries", noted)
    monkeypatch.setattr(W, "build_summaries", noted)
    # Laid out before, and then views over other tables: the curves read their own ones.
    W.laid_out(spark, str(tmp_path), "access_log")
    W.tables(spark, tiny.replace("sf0.001", "sf0.01"))
    rows = Q.exp_indexing(spark, str(tmp_path)).collect()
    assert [(r.build, r["columns"]) for r in rows] == [(f"hybrid-{h}", n) for n in (1, 2, 4, 6) for h in ("joint", "separate")] + [(f"minmax-{h}", n) for n in (1, 2, 4, 8) for h in ("scan", "footers")]
    assert all(r.seconds > 0 and r.bytes > 0 for r in rows)
    assert [len(i) for _, i in built] == [1, 2, 4, 6, 1, 2, 4, 8]
    log, grid = built[0][0].read(spark), built[-1][0].read(spark)
    W.tables(spark, tiny)
    held = lambda df, by: {r[0]: r[1:] for r in df.groupBy(F.expr(by)).agg(F.count("*"), F.sum("l_orderkey"), F.sum("city_length")).collect()}
    view = spark.sql(W.READINGS).withColumn("city_length", F.length("city"))
    assert held(grid, "obj") == held(grid, "cell") == held(view, W.CELL)
    assert log.count() == spark.sql(W.ACCESS_LOG).count()


def test_short_lists_and_filters_share_a_scan(spark, tmp_path):
    at = str(tmp_path / "rows")
    sizes = F.when(F.col("id") % 3 == 0, F.col("id") % 4).when(F.col("id") % 3 == 1, F.col("id"))  # 4 values, many, none
    spark.range(600).select(F.concat(F.lit("obj="), F.col("id") % 3).alias("path"), sizes.alias("c0")).write.parquet(at)
    rows = spark.read.parquet(at)
    first = build.materialise(rows.groupBy("path").agg(F.count("c0").alias("n_nonnull")), "first")
    made = Hybrid("c", threshold=10).second_pass(rows, first)
    held = {r.path: r.hybrid__c for r in made.collect()}
    assert {p: (s.v, s.vs, s.words is None) for p, s in held.items()} == {"obj=0": (4, [0, 1, 2, 3], True), "obj=1": (200, None, False), "obj=2": (0, None, True)}
    # A semi join with the objects of few values went below the distinct values, which were then scanned for it alone.
    assert "LeftSemi" not in made._jdf.queryExecution().optimizedPlan().toString()
