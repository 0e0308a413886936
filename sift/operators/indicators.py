"""How well skipping works: selectivity, layout, metadata and scanning factors, by query and for workloads."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sift.session import SiftSession, usable

FACTORS = ("sigma", "lambda", "mu", "psi")


def object_facts(session: SiftSession, lake: str, queries: Iterable[tuple[str, str]]) -> DataFrame:
    """(query, path, n_rows, n_relevant, keep, size): one pass over the lake counts the relevant rows of all queries."""
    queries = list(queries)
    x = session.lakes[lake]
    spark = session.spark
    df = x.source.read(spark)
    counted = x.source.tagged(df, *(F.expr(p).alias(f"q{i}") for i, (_, p) in enumerate(queries))).groupBy("path").agg(F.count("*").alias("n_rows"), *(F.count_if(F.coalesce(f"q{i}", F.lit(False))).alias(f"q{i}") for i in range(len(queries))))
    named = F.explode(F.array(*(F.struct(F.lit(name).alias("query"), F.col(f"q{i}").alias("n_relevant")) for i, (name, _) in enumerate(queries)))).alias("q")
    relevant = counted.select("path", "n_rows", named).select("path", "n_rows", "q.query", "q.n_relevant")
    from sift.plans import bridge
    from sift.plans.labelling import fold, label

    listing = x.source.listing(spark)
    matchers = usable(x)
    tests = []
    for name, p in queries:
        uses = bridge.relations(df.where(p))
        tests.append((name, fold(label(uses[0].predicate, matchers)) if uses else None))
    needed = set().union(*(t.needs() for _, t in tests if t is not None)) if tests else set()
    known = x.store.rows(needed)
    keep = F.explode(F.array(*(F.struct(F.lit(name).alias("query"), (x.store.translate(t) if t is not None else F.lit(False)).alias("holds")) for name, t in tests))).alias("k")
    told = known.where("n_rows > 0").select("path", "mtime", "size", keep).select("path", "mtime", "size", "k.query", "k.holds")
    listed = listing.join(told, ["path", "mtime", "size"], "left").select("path", "size", "query", F.coalesce("holds", F.lit(True)).alias("keep"))
    return relevant.join(listed, ["path", "query"])


def indicators(facts: DataFrame) -> DataFrame:
    """(query, sigma, lambda, mu, psi, objects, relevant, kept) by query; sigma = 0 leaves the factors undefined (null)."""
    d = lambda a, b: F.when(F.sum("n_relevant") > 0, F.sum(a) / F.sum(b))
    held = facts.select("query", "n_rows", "n_relevant", "keep", F.when(F.col("n_relevant") > 0, F.col("n_rows")).otherwise(0).alias("in_relevant"), F.when(F.col("keep"), F.col("n_rows")).otherwise(0).alias("in_kept"))
    return held.groupBy("query").agg(
        (F.sum("n_relevant") / F.sum("n_rows")).alias("sigma"), d("n_relevant", "in_relevant").alias("lambda"), d("in_relevant", "in_kept").alias("mu"), d("in_kept", "n_rows").alias("psi"),
        F.count("*").alias("objects"), F.count_if(F.expr("n_relevant > 0")).alias("relevant"), F.count_if(F.col("keep")).alias("kept"),
    )


def workload(by_query: DataFrame) -> DataFrame:
    """Geometric means of the factors over the queries that have relevant rows, and the lowest scanning factor possible."""
    gm = [F.exp(F.avg(F.ln(c))).alias(c) for c in FACTORS]
    return by_query.where("sigma > 0").agg(F.count("*").alias("queries"), *gm).withColumn("lowest_psi", F.col("sigma") / F.col("lambda"))


def identity_error(by_query: DataFrame) -> DataFrame:
    """Largest deviation from psi = sigma / (lambda mu)."""
    return by_query.where("sigma > 0").agg(F.max(F.abs(F.col("psi") - F.col("sigma") / (F.col("lambda") * F.col("mu")))).alias("error"))


def false_positives(facts: DataFrame) -> DataFrame:
    """(query, false_positives, ratio): kept objects without relevant rows, and their share of the irrelevant ones."""
    return facts.groupBy("query").agg(F.count_if(F.expr("keep AND n_relevant = 0")).alias("false_positives"), (F.count_if(F.expr("keep AND n_relevant = 0")) / F.greatest(F.count_if(F.expr("n_relevant = 0")), F.lit(1))).alias("ratio"))


def unsound(facts: DataFrame) -> DataFrame:
    """Objects with relevant rows that would be skipped: there must be none."""
    return facts.where("n_relevant > 0 AND NOT keep")


def layout_verdict(by_query: DataFrame, limit: float = 0.5) -> DataFrame:
    """(query, lowest_psi, hopeless): whether even perfect metadata would scan more than ``limit`` of the rows."""
    lowest = F.col("sigma") / F.col("lambda")
    return by_query.where("sigma > 0").select("query", lowest.alias("lowest_psi"), (lowest > limit).alias("hopeless"))
