"""Index selection, gap choice, cost models, layouts, stores."""

import random

import pytest
from pyspark.sql import functions as F

from sift.functions import geo
from sift.operators import selection
from sift.operators.build import build_summaries, refresh_summaries
from sift.operators.kinds import Bloom, MinMax, ValueList, default_kinds
from sift.operators.report import kind_line_counts, scans
from sift.runtime import scratch_path
from sift.session import SiftSession
from sift.sources.lake import LakeSource
from sift.sources.layouts import kd_leaf
from sift.sources.stores import ParquetSummaryStore


def test_hybrid_threshold():
    assert selection.hybrid_threshold(64e6, 512, 0.01, 0.01) == 10_088
    t = [selection.hybrid_threshold(64e6, 512, f, 0.01) for f in (0.001, 0.01, 0.1)]
    assert t == sorted(t)
    e = [selection.hybrid_threshold(64e6, 512, 0.01, s) for s in (0.01, 0.5, 0.9)]
    assert e == sorted(e, reverse=True)
    for v in (10_000, 10_088, 10_089, 10_200):
        a, b = (selection.expected_scan_bytes(k, 64e6, v, 512, 0.01, [True] + [False] * 99) for k in ("list", "bloom"))
        assert (a < b) == (v <= 10_088)


def test_knapsack_against_enumeration():
    rnd = random.Random(3)
    for _ in range(60):
        c = [(f"i{k}", rnd.choice([0, 1, 5, 9, 14, 60]), round(rnd.random(), 3)) for k in range(rnd.randrange(1, 11))]
        budget = rnd.randrange(0, 60)
        worth = {n: v for n, _, v in c}
        cost = {n: w for n, w, _ in c}
        value = {m: sum(worth[n] for n in selection.select_indexes(c, budget, m)) for m in ("exact", "dp", "greedy")}
        assert all(sum(cost[n] for n in selection.select_indexes(c, budget, m)) <= budget for m in value)
        assert value["dp"] == pytest.approx(value["exact"]) and 2 * value["greedy"] >= value["exact"] - 1e-9


def test_marginal_selection_stops_at_perfect_metadata():
    keeps = {"perfect": [0b001, 0b010], "coarse": [0b011, 0b110], "useless": [0b111, 0b111]}
    assert selection.select_marginal({"perfect": 10, "coarse": 1, "useless": 1}, keeps, [5, 5, 5], 100) == ["coarse", "perfect"]
    assert selection.select_marginal({"perfect": 10, "coarse": 30, "useless": 1}, keeps, [5, 5, 5], 100) == ["perfect"]


def test_gap_choice_on_hypergraphs():
    rnd = random.Random(4)
    for _ in range(40):
        n = rnd.randrange(3, 8)
        values, queries = selection.hypergraph_workload(n, [rnd.sample(range(n), rnd.randrange(1, 4)) for _ in range(rnd.randrange(1, 8))])
        gaps = list(zip(values, values[1:], strict=False))
        skipped = lambda held: sum(all(any(gaps[g][0] < a and b < gaps[g][1] for g in held) for a, b in q) for q in queries)  # noqa: E731, B023
        for k in (1, 2, 3):
            best, greedy = (selection.choose_gaps_disjunctive(gaps, queries, k, m) for m in ("exact", "greedy"))
            assert len(greedy) <= k and skipped(greedy) <= skipped(best)


def test_polygons():
    ring = geo.ring_of("POLYGON((0 0, 4 0, 4 4, 2 1, 0 4, 0 0))")
    assert not geo.is_convex(ring) and geo.is_convex(geo.ring_of("POLYGON((0 0, 4 0, 2 3))"))
    with pytest.raises(ValueError):
        geo.ring_of("POINT(1 2)")
    import numpy as np

    x, y = np.random.default_rng(1).uniform(-1, 5, (2, 500))
    inside = geo.contains_numpy(ring, x, y)
    notch = (y < 4 - 1.5 * x) | (y < 1.5 * x - 2)  # below the notch's sides
    assert (inside == ((x > 0) & (x < 4) & (y > 0) & notch)).mean() == 1.0


def test_kd_leaves_are_even(spark):
    df = spark.range(4000).select((F.rand(1) * 10).alias("x"), (F.rand(2) ** 3).alias("y"))
    n = [r["count"] for r in kd_leaf(df, ["x", "y"], 8).groupBy("leaf").count().collect()]
    assert len(n) == 8 and max(n) < 1.2 * min(n)


def test_default_kinds_and_lines(spark, tiny):
    ks = default_kinds(spark.read.parquet(f"{tiny}/orders.parquet").schema)
    assert all(k.bounded for k in ks) and {k.index for k in ks} >= {"minmax__o_orderkey", "bloom__o_orderstatus"}
    assert max(kind_line_counts().values()) < 60


@pytest.fixture()
def events(spark, tiny):
    path = scratch_path(spark, "design")
    spark.read.parquet(f"{tiny}/events.parquet").repartitionByRange(8, "event_id").write.parquet(path)
    return LakeSource(path)


def test_old_batches_unknown_kinds_and_cache(spark, events):
    store = ParquetSummaryStore(spark, scratch_path(spark, "old"))
    build_summaries(spark, events, [MinMax("event_id"), Bloom("user_id"), ValueList("event_type")], store)
    s = SiftSession(spark, cached=True)
    s.add("e", events, store, [MinMax("event_id"), MinMax("value")])  # no summary of value was built: it is not used
    for _ in range(2):
        assert s.sql("SELECT count(*) FROM e WHERE event_id < 10 AND value >= 0").first()[0] == 10
    assert len(s.history[-1].kept) == 1
    r = refresh_summaries(spark, events, [MinMax("event_id"), Bloom("user_id"), ValueList("event_type")], store)
    assert (r.added, r.rebuilt, r.dropped, r.untouched) == (0, 0, 0, 8)


def test_many_keys_are_packed(spark, events, monkeypatch):
    import sift.sources.lake as lake_module

    store = ParquetSummaryStore(spark, scratch_path(spark, "packed"))
    build_summaries(spark, events, [MinMax("event_id")], store)
    s = SiftSession(spark)
    s.add("e", events, store, [MinMax("event_id")])
    monkeypatch.setattr(lake_module, "IN_LIST", 2)
    df = s.sql("SELECT event_id FROM e WHERE event_id < 10")
    assert len(df.collect()) == 10 and scans(df)[0].files == 1


def _new_rows(spark, n=3):
    return spark.range(n).selectExpr("id AS event_id", "timestamp_ntz'2024-01-01' AS ts", "0L AS user_id", "'new' AS event_type", "0D AS value", "'' AS props").coalesce(1)


@pytest.mark.parametrize("in_list", [5000, 2])
def test_large_lakes_name_skipped_objects_only(spark, events, monkeypatch, in_list):
    """Digests of the skipped objects; whatever came or changed since is read, also files moved in with an old time."""
    import os

    import sift.session as session_module
    import sift.sources.lake as lake_module

    store = ParquetSummaryStore(spark, scratch_path(spark, "large"))
    build_summaries(spark, events, [MinMax("event_id")], store)
    monkeypatch.setattr(session_module, "COLLECT", 2)
    monkeypatch.setattr(lake_module, "IN_LIST", in_list)
    s = SiftSession(spark)
    s.add("e", events, store, [MinMax("event_id")])
    text = "SELECT event_id FROM e WHERE event_id < 10"
    df = s.sql(text)
    decision = s.history[-1]
    assert len(df.collect()) == 10 and decision.digests and len(decision.skipped) == 7 and scans(df)[0].files == 1
    _new_rows(spark).write.mode("append").parquet(events.path)
    assert s.prune(events.read(spark), decision).where("event_type = 'new'").count() == 3  # came after the listing
    elsewhere = scratch_path(spark, "moved")
    _new_rows(spark, 5).write.parquet(elsewhere)
    (moved,) = [f for f in os.listdir(elsewhere.removeprefix("file://")) if f.endswith(".parquet")]
    old = elsewhere.removeprefix("file://") + "/" + moved
    os.utime(old, (10**9, 10**9))
    os.rename(old, events.path.removeprefix("file://") + "/part-moved.parquet")
    assert s.prune(events.read(spark), decision).where("event_type = 'new'").count() == 8
    assert len(s.sql(text).collect()) == 18 and s.history[-1].n_kept == 3
    df = s.sql("SELECT event_id FROM e WHERE event_id >= 0 AND event_id <> 7")
    assert len(df.collect()) == events.read(spark).where("event_id <> 7").count() and s.history[-1].skipped == []


def test_files_of_one_clock_tick(spark, events, monkeypatch):
    """Many files of one modification time are pruned all the same."""
    import os

    import sift.session as session_module

    folder = events.path.removeprefix("file://")
    for f in os.listdir(folder):
        os.utime(f"{folder}/{f}", (1_700_000_000, 1_700_000_000))
    store = ParquetSummaryStore(spark, scratch_path(spark, "tick"))
    build_summaries(spark, events, [MinMax("event_id")], store)
    monkeypatch.setattr(session_module, "COLLECT", 2)
    s = SiftSession(spark)
    s.add("e", events, store, [MinMax("event_id")])
    df = s.sql("SELECT event_id FROM e WHERE event_id < 10")
    assert len(df.collect()) == 10 and scans(df)[0].files == 1


def test_other_parameters_than_stored(spark, events):
    """An index is used only by a kind of the very parameters that it was built with."""
    from sift.operators.kinds import GapList, Hybrid, RangeBits, Template

    built = [Bloom("user_id", fpp=0.01), RangeBits("value", 0.0, 400.0), Template("props", "get_json_object(props, '$.k')", "k"), Hybrid("event_type", threshold=2), GapList("event_id", 4)]
    asked = [Bloom("user_id", fpp=1e-6), RangeBits("value", 0.0, 4000.0), Template("props", "substring(props, 1, 3)", "k"), Hybrid("event_type", threshold=3), GapList("event_id", 5)]
    store = ParquetSummaryStore(spark, scratch_path(spark, "params"))
    build_summaries(spark, events, built, store)
    one = events.read(spark).first()
    for kinds, used in ((built, True), (asked, False)):
        s = SiftSession(spark)
        s.add("e", events, store, kinds)
        for text in (f"user_id = {one.user_id}", f"value > {one.value - 1} AND value < {one.value + 1}", f"event_type = '{one.event_type}'", f"event_id BETWEEN {one.event_id} AND {one.event_id + 5}"):
            assert s.sql(f"SELECT event_id FROM e WHERE {text}").count() == events.read(spark).where(text).count() > 0
            assert (s.history[-1].test.sql() != "true") == used, text
    with pytest.raises(ValueError):
        build_summaries(spark, events, asked[:1], store, mode="append")
    assert MinMax("a.b").index != MinMax("a_b").index and MinMax("a_b").index == "minmax__a_b"


def test_many_batches_are_merged(spark, events, monkeypatch):
    import sift.sources.stores as stores_module

    monkeypatch.setattr(stores_module, "COMPACT_AFTER", 6)
    path, kinds = scratch_path(spark, "compact"), [MinMax("event_id"), ValueList("event_type", key_id="k")]
    store = ParquetSummaryStore(spark, path, {"k": b"0123456789abcdef"})
    for n in range(20):
        build_summaries(spark, events, kinds, store, mode="append" if n else "replace")
        assert len(store.manifest()["batches"]) <= 6
    rows = store.rows([k.index for k in kinds])
    assert rows.count() == 8 == rows.where("minmax__event_id.lo IS NOT NULL AND size(list__event_type.vs) > 0").count()
    assert "click" not in str(spark.read.parquet(f"{path}/batch-*").select("list__event_type").distinct().collect())
    assert store.read_bytes(["minmax__event_id"]) < store.read_bytes([k.index for k in kinds]) <= store.bytes()


def test_a_crash_between_commits_loses_nothing(spark, events, monkeypatch):
    store = ParquetSummaryStore(spark, scratch_path(spark, "crash"))
    build_summaries(spark, events, [MinMax("event_id")], store)
    before = store.manifest()
    monkeypatch.setattr(ParquetSummaryStore, "_commit", lambda self, m, after: (_ for _ in ()).throw(OSError("lost")))
    with pytest.raises(OSError):
        build_summaries(spark, events, [MinMax("event_id"), MinMax("value")], store)
    monkeypatch.undo()
    assert store.manifest() == before and store.rows(["minmax__event_id"]).count() == 8
    with pytest.raises(RuntimeError):  # two writers after one version: the second is told
        store._commit(before, before["version"] - 1)


def test_functions_of_columns_and_nulls(spark):
    """Queries, polygons and shapes that differ by row; nulls give null."""
    from sift.functions import distance

    geo.register(spark)
    distance.register(spark)
    tri, box = "POLYGON((0 0, 4 0, 0 4))", "POLYGON((10 10, 12 10, 12 12, 10 12))"
    rows = [([1.0, 2.0], "1,2", tri, 1.0, 1.0), ([1.0, 2.0], "4,6", box, 11.0, 11.0), (None, "1,2", box, 1.0, 1.0), ([1.0], "1,2", tri, None, 1.0), ([0.0, 0.0], None, None, 1.0, 1.0)]
    df = spark.createDataFrame(rows, "v array<double>, q string, wkt string, lat double, lng double")
    got = df.selectExpr("euclid_distance(v, q) AS e", "manhattan_distance(v, q) AS m", "st_contains(wkt, lat, lng) AS c").collect()
    assert [r.e for r in got] == [0.0, 5.0, None, None, None] and [r.m for r in got] == [0.0, 7.0, None, None, None]
    assert [r.c for r in got] == [True, True, False, None, None]
    ring = lambda *p: [{"x": x, "y": y} for x, y in p]
    shapes = [(ring((0.0, 0.0), (4.0, 0.0), (0.0, 4.0)), 1.0, 1.0), (ring((0.0, 0.0), (4.0, 0.0), (0.0, 4.0)), 3.0, 3.0), (None, 1.0, 1.0), ([], 1.0, 1.0), (ring((0.0, 0.0), (4.0, None), (0.0, 4.0)), 1.0, 1.0), (ring((0.0, 0.0), (9.0, 0.0), (9.0, 9.0), (0.0, 9.0)), None, 2.0), (ring((0.0, 0.0), (9.0, 0.0), (9.0, 9.0), (0.0, 9.0)), 8.0, 2.0)]
    df = spark.createDataFrame(shapes, "s array<struct<x:double,y:double>>, lat double, lng double")
    got = df.selectExpr("st_shape_contains(s, lat, lng) AS c", f"st_shape_intersects('{tri}', s) AS i", "st_shape_intersects(NULL, s) AS n").collect()
    assert [r.c for r in got] == [True, False, None, None, None, None, True]
    assert [r.i for r in got] == [True, True, None, None, None, True, True] and {r.n for r in got} == {None}


def test_only_ciphertext_is_stored(spark, events):
    path = scratch_path(spark, "sealed")
    build_summaries(spark, events, [ValueList("event_type", key_id="k")], ParquetSummaryStore(spark, path, {"k": b"0123456789abcdef"}))
    told = spark.read.parquet(f"{path}/batch-*").select("list__event_type").first()[0]
    assert "click" not in told
    assert ParquetSummaryStore(spark, path).hidden() == ["list__event_type"]


def test_reregistered_function_loses_its_matcher(spark, events):
    from sift.plans.labelling import Matcher

    store = ParquetSummaryStore(spark, scratch_path(spark, "fn"))
    build_summaries(spark, events, [MinMax("value")], store)
    s = SiftSession(spark)
    s.add("e", events, store, [MinMax("value")])

    class Positive(Matcher):
        def match(self, node):
            if node.kind == "call" and node.term.name == "is_high":
                yield MinMax("value").test("{s}.hi > 300")

    s.register_function("is_high", F.udf(lambda v: v > 300, "boolean"), Positive(), "e")
    n = s.sql("SELECT count(*) FROM e WHERE is_high(value)").first()[0]
    assert n == events.read(spark).where("value > 300").count() and s.history[-1].skipped
    s.register_function("is_high", F.udf(lambda v: v > 0, "boolean"))
    assert s.sql("SELECT count(*) FROM e WHERE is_high(value)").first()[0] == events.read(spark).where("value > 0").count()
    assert not s.history[-1].skipped


def test_registry_rebuilds_kinds_from_a_manifest(spark, events):
    from sift import registry

    store = ParquetSummaryStore(spark, scratch_path(spark, "registry"))
    kinds = [MinMax("event_id"), Bloom("user_id", fpp=0.02), ValueList("event_type")]
    build_summaries(spark, events, kinds, store)
    again = [registry.kind_of(d) for d in store.indexes().values()]
    assert sorted(k.index for k in again) == sorted(k.index for k in kinds)
    s = SiftSession(spark)
    s.add("e", events, store, again)
    assert s.sql("SELECT count(*) FROM e WHERE event_id < 10").first()[0] == 10 and len(s.history[-1].kept) == 1
    assert registry.kind_of({"kind": "from-the-future", "columns": ["a"], "params": {}, "key_id": None}) is None
    assert s.history_frame().count() == 1


def test_shapes_intersect():
    a = geo.ring_of("POLYGON((0 0, 4 0, 4 4, 0 4))")
    assert geo.rings_intersect(a, geo.ring_of("POLYGON((3 3, 9 3, 9 9))"))
    assert geo.rings_intersect(a, geo.ring_of("POLYGON((1 1, 2 1, 2 2))")) and geo.rings_intersect(geo.ring_of("POLYGON((1 1, 2 1, 2 2))"), a)
    assert not geo.rings_intersect(a, geo.ring_of("POLYGON((5 5, 9 5, 9 9))"))
    assert geo.rings_intersect(geo.ring_of("POLYGON((-1 1, 5 1, 5 2, -1 2))"), geo.ring_of("POLYGON((1 -1, 2 -1, 2 5, 1 5))"))


def test_views_over_lakes(spark, events):
    """A view over a lake sees files that came since, and no pruning of an earlier query stays behind."""
    store = ParquetSummaryStore(spark, scratch_path(spark, "views"))
    build_summaries(spark, events, [MinMax("event_id")], store)
    s = SiftSession(spark)
    s.add("seen_lake", events, store, [MinMax("event_id")])
    spark.sql("CREATE OR REPLACE TEMP VIEW over_it AS SELECT event_id, event_type FROM seen_lake")
    n = events.read(spark).count()
    assert s.sql("SELECT count(*) FROM seen_lake WHERE event_id < 10").first()[0] == 10 and s.history[-1].skipped
    assert spark.sql("SELECT count(*) FROM seen_lake").first()[0] == n == s.sql("SELECT count(*) FROM over_it").first()[0]
    _new_rows(spark).write.mode("append").parquet(events.path)
    assert s.sql("SELECT count(*) FROM over_it WHERE event_type = 'new'").first()[0] == 3
    assert s.sql("SELECT count(*) FROM over_it WHERE event_id < 10").first()[0] == 13 and s.history[-1].skipped
