"""Summaries and tests that must stay small where an object has many values, or a predicate many literals."""

from pyspark.sql import functions as F

from sift.operators.kinds import Bloom, Hybrid, MinMax
from sift.plans.predicate import Lit, Node, Ref


def _given(spark, n):
    rows = spark.range(n).select(F.concat(F.lit("obj="), F.col("id") % 3).alias("path"), F.col("id").alias("c0"))
    first = rows.select("path").distinct().union(spark.createDataFrame([("obj=none",)], "path string")).withColumn("n_nonnull", F.lit(1).cast("long"))
    return rows, first


def test_filter_words_are_gathered_without_a_map(spark):
    rows, first = _given(spark, 3000)
    for kind, name in ((Bloom("c"), "bloom__c"), (Hybrid("c", threshold=10), "hybrid__c")):
        made = kind.second_pass(rows, first)
        # A map of the words is made again for every word once the optimizer has put it into the lambda.
        assert "map_from_entries" not in made._jdf.queryExecution().optimizedPlan().toString()
        held = {r.path: r[name] for r in made.collect()}
        assert held["obj=none"].v == 0 and held["obj=none"].words is None
        for k in range(3):
            s = held[f"obj={k}"]
            want = [0] * ((s.m - 1) // 64 + 1)
            for r in rows.where(F.col("path") == f"obj={k}").select(*(F.expr(f"pmod(xxhash64(c0, {i}), {s.m})") for i in range(kind.hashes))).collect():
                for bit in r:
                    want[bit // 64] |= 1 << bit % 64
            assert s.v == 1000 and [w % 2**64 for w in s.words] == want


def test_many_literals_are_tested_by_one_expression(spark):
    rows, first = _given(spark, 3000)
    bloom, hybrid, bounds = Bloom("c"), Hybrid("c", threshold=10), MinMax("c")
    made = bloom.second_pass(rows, first).join(hybrid.second_pass(rows, first), "path").join(rows.groupBy("path").agg(F.struct(F.count("*").alias("n_nonnull"), F.min("c0").alias("lo"), F.max("c0").alias("hi")).alias("minmax__c")), "path").withColumn("n_rows", F.lit(1)).cache()
    for low, kept in ((0, {0, 1, 2}), (10**6, set())):
        for step in (1, 3):  # all objects, or obj=0 only
            node = Node("in", term=Ref("c", "long"), values=tuple(Lit(str(low + step * i), "long") for i in range(900)))
            for kind in (bloom, hybrid, bounds):
                (test,) = kind.match(node)
                assert len(test.sql()) < 40 * len(node.values), kind.kind
                got = {int(r.path[-1]) for r in made.where(test.sql()).collect()}
                # Bounds can't tell residues apart, and the filters may err by keeping.
                assert got >= (kept & {0} if step == 3 else kept)
                if low and kind is bounds:
                    assert not got


def test_many_literals_of_other_types(spark):
    made = spark.createDataFrame([(["a'b", "\\", "x,y"],)], "c0 array<string>").select(F.lit("p").alias("path"), F.explode("c0").alias("c0"))
    first = spark.createDataFrame([("p", 3)], "path string, n_nonnull long")
    held = Bloom("c").second_pass(made, first)
    for extra, keep in (("x,y", 1), ("\\", 1), ("a'b", 1), ("x", 0)):
        values = tuple(Lit(v, "string") for v in (*(f"no,{i}" for i in range(20)), extra))
        (test,) = Bloom("c").match(Node("in", term=Ref("c", "string"), values=values))
        assert held.where(test.sql()).count() >= keep, extra
