"""Queries of the measures: indicators, cost models, selection, sweeps."""

from __future__ import annotations

from pyspark.sql import functions as F

from sift import workloads as W
from sift.cases import query
from sift.operators import build, indicators, report, selection
from sift.operators.baselines import without_skipping
from sift.operators.kinds import Bloom, BoxSet, GapList, GeoMinMax, Hybrid, MetricRing, MinMax, PrefixList, RangeBits, SuffixList, Template, ValueList
from sift.runtime import scratch_path
from sift.sources.lake import LakeSource
from sift.sources.layouts import write_by
from sift.sources.stores import ParquetSummaryStore

_OBJ = "strftime(ts, '%Y-%m-%d') || '-' || CAST(user_id % 4 AS VARCHAR)"
#: Order in which rows are drawn: by a seeded hash that Spark and DuckDB share.
_DRAWN = "md5('5:' || CAST(event_id AS STRING)), event_id"


def _queries(spark, column: str, n: int, suffix: bool, cap: int = 200) -> list[tuple[str, str]]:
    """(name, piece): heads or tails of the values at ``n`` rows drawn from the whole table, of a length that depends on the row."""
    cut = "right" if suffix else "left"
    rows = spark.sql(f"SELECT event_id, {cut}({column}, cast(1 + (event_id * 7) % least(length({column}), {cap}) AS int)) AS piece FROM access_log ORDER BY {_DRAWN} LIMIT {n}").collect()
    return [(f"q{r.event_id}", r.piece) for r in rows]


def _factors(column: str, n: int, suffix: bool, length: int) -> str:
    """The four factors in SQL, on the objects' logical ids and the kind's definition."""
    cut, fits = ("right", "ends_with") if suffix else ("left", "starts_with")
    return f""", q AS (SELECT 'q' || CAST(event_id AS VARCHAR) AS query, {cut}({column}, CAST(1 + (event_id * 7) % least(length({column}), 200) AS INTEGER)) AS piece FROM access_log ORDER BY {_DRAWN} LIMIT {n}),
r AS (SELECT {_OBJ} AS obj, {column} AS v, count(*) AS n FROM access_log GROUP BY 1, 2),
o AS (SELECT query, obj, sum(n) AS n_rows, sum(CASE WHEN {fits}(v, piece) THEN n ELSE 0 END) AS n_relevant,
      bool_or({fits}({cut}(v, {length}), {cut}(piece, {length}))) AS keep FROM r, q GROUP BY 1, 2),
s AS (SELECT query, sum(n_rows) AS d, sum(n_relevant) AS dr, sum(CASE WHEN n_relevant > 0 THEN n_rows ELSE 0 END) AS r, sum(CASE WHEN keep THEN n_rows ELSE 0 END) AS m FROM o GROUP BY 1)
"""


def _rounded(df):
    return df.select("query", *(F.round(c, 9).alias(c) for c in indicators.FACTORS))


_ROUNDED = "SELECT query, round(dr / d, 9) AS sigma, round(dr / r, 9) AS lambda, round(r / m, 9) AS mu, round(m / d, 9) AS psi FROM s"


def _text_facts(spark, sf_dir, column: str, kind, n: int = 50):
    s = W.session(spark, sf_dir, "access_log")
    x = s.lakes["access_log"]
    suffix = kind.kind == "suffix"
    s.add("access_log", x.source, x.store, [kind])
    fits = "endswith" if suffix else "startswith"
    return indicators.object_facts(s, "access_log", [(name, f"{fits}({column}, '{piece}')") for name, piece in _queries(spark, column, n, suffix)])


for _key, _column, _kind in (("ind_prefix", "db_name", PrefixList("db_name", 15)), ("ind_suffix", "db_name", SuffixList("db_name", 15)), ("ind_request", "http_request", PrefixList("http_request", 20))):

    def _run(spark, sf_dir, column=_column, kind=_kind):
        return _rounded(indicators.indicators(_text_facts(spark, sf_dir, column, kind)))

    query(_key, _factors(_column, 50, _kind.kind == "suffix", _kind.params["length"]) + _ROUNDED, "access_log")(_run)


def _agent_facts(spark, sf_dir, lake: str):
    s = W.session(spark, sf_dir, lake)
    x = s.lakes[lake]
    s.add(lake, x.source, x.store, [k for k in x.kinds if isinstance(k, Template)])
    drawn = spark.sql(f"SELECT event_id, {W.AGENT} AS a FROM {lake} ORDER BY {_DRAWN} LIMIT 50").collect()
    return indicators.object_facts(s, lake, [(f"q{r.event_id}", f"{W.AGENT} = '{r.a}'") for r in drawn])


def _agent_factors(obj: str) -> str:
    return f""", v AS (SELECT {obj} AS obj, regexp_extract(user_agent, '^([^/]+)', 1) AS a FROM access_log), t AS (SELECT obj, count(*) AS n FROM v GROUP BY 1), q AS (SELECT 'q' || CAST(event_id AS VARCHAR) AS query, regexp_extract(user_agent, '^([^/]+)', 1) AS a FROM access_log ORDER BY {_DRAWN} LIMIT 50), c AS (SELECT query, obj, count(*) AS n FROM v JOIN q USING (a) GROUP BY 1, 2),
s AS (SELECT query, (SELECT count(*) FROM v) AS d, sum(c.n) AS dr, sum(t.n) AS r, sum(t.n) AS m FROM c JOIN t USING (obj) GROUP BY 1)
"""


@query("ind_agent", _agent_factors(_OBJ) + _ROUNDED, "access_log")
def ind_agent(spark, sf_dir):
    return _rounded(indicators.indicators(_agent_facts(spark, sf_dir, "access_log")))


@query("ind_agent_hourly", _agent_factors("strftime(ts, '%Y-%m-%d') || '-' || CAST(hour(ts) // 3 AS VARCHAR)") + _ROUNDED, "access_log")
def ind_agent_hourly(spark, sf_dir):
    return _rounded(indicators.indicators(_agent_facts(spark, sf_dir, "hourly_log")))


_MEANS = "SELECT count(*) AS queries, round(exp(avg(ln(dr / d))), 9) AS sigma, round(exp(avg(ln(dr / r))), 9) AS lambda, round(exp(avg(ln(r / m))), 9) AS mu, round(exp(avg(ln(m / d))), 9) AS psi FROM s"


@query("ind_geomean", _factors("db_name", 50, False, 15) + _MEANS, "access_log")
def ind_geomean(spark, sf_dir):
    means = indicators.workload(indicators.indicators(_text_facts(spark, sf_dir, "db_name", PrefixList("db_name", 15))))
    return means.select("queries", *(F.round(c, 9).alias(c) for c in indicators.FACTORS))


@query("ind_identity", "SELECT 0.0 AS error")
def ind_identity(spark, sf_dir):
    """psi = sigma / (lambda mu), for every query."""
    return indicators.identity_error(indicators.indicators(_text_facts(spark, sf_dir, "db_name", SuffixList("db_name", 15)))).select(F.round("error", 12).alias("error"))


@query("ind_sound", "SELECT 0 AS lost")
def ind_sound(spark, sf_dir):
    """Objects with relevant rows that the prefix, suffix or list summaries would skip: none."""
    lost = None
    for k in (PrefixList("db_name", 15), SuffixList("db_name", 15)):
        bad = indicators.unsound(_text_facts(spark, sf_dir, "db_name", k))
        lost = bad if lost is None else lost.unionByName(bad)
    return lost.agg(F.count("*").cast("int").alias("lost"))


@query("ind_false_positives", _factors("db_name", 50, False, 15) + "SELECT query, CAST(sum(CASE WHEN keep AND n_relevant = 0 THEN 1 ELSE 0 END) AS BIGINT) AS false_positives FROM o GROUP BY 1", "access_log")
def ind_false_positives(spark, sf_dir):
    return indicators.false_positives(_text_facts(spark, sf_dir, "db_name", PrefixList("db_name", 15))).select("query", "false_positives")


@query("ind_lowest_psi", _factors("db_name", 50, False, 15) + "SELECT query, round(r / d, 9) AS lowest_psi, r / d > 0.5 AS hopeless FROM s", "access_log")
def ind_lowest_psi(spark, sf_dir):
    """What perfect metadata would scan under this layout."""
    v = indicators.layout_verdict(indicators.indicators(_text_facts(spark, sf_dir, "db_name", PrefixList("db_name", 15))))
    return v.select("query", F.round("lowest_psi", 9).alias("lowest_psi"), "hopeless")


LENGTHS = (3, 6, 9, 12, 15, 20, 30, 200)


@query("sweep_prefix_length", " UNION ALL ".join(f"SELECT {n} AS length, * FROM (WITH {W.oracle_views('access_log')[5:-1]}" + _factors("db_name", 20, False, n) + "SELECT round(exp(avg(ln(r / m))), 9) AS mu, round(exp(avg(ln(m / d))), 9) AS psi FROM s)" for n in LENGTHS))
def sweep_prefix_length(spark, sf_dir):
    """Metadata and scanning factor by prefix length; the longest stands for whole values."""
    source, _, _ = W.lake(spark, sf_dir, "access_log")
    out = None
    store, kinds = ParquetSummaryStore(spark, scratch_path(spark, "sweep")), [PrefixList("db_name", n) for n in LENGTHS]
    build.build_summaries(spark, source, kinds, store)
    for n, kind in zip(LENGTHS, kinds, strict=True):
        s = W.session(spark, sf_dir, "access_log")
        s.add("access_log", source, store, [kind])
        facts = indicators.object_facts(s, "access_log", [(q, f"startswith(db_name, '{p}')") for q, p in _queries(spark, "db_name", 20, False)])
        m = indicators.workload(indicators.indicators(facts)).select(F.lit(n).alias("length"), F.round("mu", 9).alias("mu"), F.round("psi", 9).alias("psi"))
        out = m if out is None else out.union(m)
    return out


@query("sweep_prefix_bytes")
def sweep_prefix_bytes(spark, sf_dir):
    """Stored bytes by prefix length, against the value list."""
    source, _, _ = W.lake(spark, sf_dir, "access_log")
    rows = []
    for kind in (*(PrefixList("db_name", n) for n in LENGTHS[:-1]), ValueList("db_name")):
        store = ParquetSummaryStore(spark, scratch_path(spark, "bytes"))
        r = build.build_summaries(spark, source, [kind], store)
        rows.append((kind.index, r.objects, r.bytes, r.seconds))
    return spark.createDataFrame(rows, "kind string, objects int, bytes long, seconds double")


# -- index selection and cost models
_PIECES = {"brand": "p_brand", "type": "p_type", "name": "p_name", "name_head": "left(p_name, 3)", "name_tail": "right(p_name, 3)", "type_head": "left(p_type, 3)", "type_tail": "right(p_type, 3)", "size": "CAST(p_size AS VARCHAR(12))", "brand_size": "p_brand || CAST(p_size AS VARCHAR(12))"}
#: Lists of values and of pieces of them as candidates, for objects of 40 parts: their bytes, and the share of objects that a value lets skip.
_CANDIDATES = "SELECT name, CAST(sum(length(v)) AS BIGINT) AS cost, round(1 - CAST(count(*) AS DOUBLE) / (count(DISTINCT v) * max(objects)), 6) AS benefit FROM (" + " UNION ALL ".join(f"SELECT DISTINCT '{n}' AS name, CAST(floor(p_partkey / 40.0) AS BIGINT) AS obj, {e} AS v FROM part WHERE {e} IS NOT NULL" for n, e in _PIECES.items()) + ") u CROSS JOIN (SELECT count(DISTINCT CAST(floor(p_partkey / 40.0) AS BIGINT)) AS objects FROM part) o GROUP BY name"
_SHARES = (10, 30, 60)
_BEST = f"WITH RECURSIVE c AS (SELECT CAST(row_number() OVER (ORDER BY name) AS INTEGER) AS i, cost, benefit FROM ({_CANDIDATES}) k), s(i, cost, benefit) AS (SELECT 0, CAST(0 AS BIGINT), CAST(0 AS DOUBLE) UNION ALL SELECT c.i, s.cost + c.cost, s.benefit + c.benefit FROM s JOIN c ON c.i > s.i), b AS (SELECT CAST(sum(cost) AS BIGINT) * unnest([{', '.join(map(str, _SHARES))}]) // 100 AS budget FROM c) SELECT budget, round(max(benefit), 6) AS benefit FROM s JOIN b ON s.cost <= b.budget GROUP BY budget"


def _candidates(spark, sf_dir) -> tuple[list, list[int]]:
    """The candidates on the given parts, and budgets as shares of their bytes."""
    W.tables(spark, sf_dir)
    found = sorted((r.name, r.cost, r.benefit) for r in spark.sql(_CANDIDATES).collect())
    return found, [sum(c for _, c, _ in found) * share // 100 for share in _SHARES]


def _worth(found: list, budget: int, method: str) -> float:
    chosen = set(selection.select_indexes(found, budget, method))
    return sum(b for n, _, b in found if n in chosen)


def _choice(method: str):
    def run(spark, sf_dir):
        found, budgets = _candidates(spark, sf_dir)
        return spark.createDataFrame([(k, round(_worth(found, k, method), 6)) for k in budgets], "budget long, benefit double")

    return run


for _m in ("dp", "exact"):
    query(f"select_{_m}", _BEST)(_choice(_m))


@query("select_greedy", f"SELECT budget, true AS at_least_half FROM ({_BEST}) t")
def select_greedy(spark, sf_dir):
    """Greedy by benefit a byte reaches at least half the optimum."""
    found, budgets = _candidates(spark, sf_dir)
    return spark.createDataFrame([(k, 2 * _worth(found, k, "greedy") >= _worth(found, k, "exact")) for k in budgets], "budget long, at_least_half boolean")


@query("select_marginal")
def select_marginal(spark, sf_dir):
    """Indexes chosen by marginal gain on real summaries: stored bytes, and what each lets be skipped over a workload."""
    s = W.session(spark, sf_dir, "access_log")
    x = s.lakes["access_log"]
    work = [(q, f"startswith(db_name, '{p}')") for q, p in _queries(spark, "db_name", 20, False)]
    costs, keeps, rows, order = {}, {}, [], []
    for kind in [k for k in x.kinds if k.columns[0] == "db_name"]:
        s.add("access_log", x.source, x.store, [kind])
        held = indicators.object_facts(s, "access_log", work).select("query", "path", "n_rows", "keep").collect()  # queries x objects
        if not order:
            order = sorted({r.path for r in held})
            rows = [next(r.n_rows for r in held if r.path == p) for p in order]
        at = {p: i for i, p in enumerate(order)}
        keeps[kind.index] = [sum(1 << at[r.path] for r in held if r.query == q and r.keep) for q, _ in work]
        path = scratch_path(spark, "cost")
        x.store.rows([kind.index]).select(kind.index).write.parquet(path)
        costs[kind.index] = spark.read.format("binaryFile").load(path).agg(F.sum("length")).first()[0]
    out = [(b, ",".join(selection.select_marginal(costs, keeps, rows, b))) for b in (min(costs.values()), sum(costs.values()))]
    return spark.createDataFrame(out, "budget long, chosen string")


_COSTS = "v * bits / 8 + hit * bytes AS list_bytes, -v * ln(CAST(0.01 AS DOUBLE)) / (ln(2) * ln(2)) / 8 + hit * bytes + (1 - hit) * CAST(0.01 AS DOUBLE) * bytes AS bloom_bytes"


@query("cost_model", f"SELECT obj, v, round(list_bytes, 3) AS list_bytes, round(bloom_bytes, 3) AS bloom_bytes, list_bytes < bloom_bytes AS list_wins FROM (SELECT obj, v, {_COSTS} FROM (SELECT *, CAST(v AS DOUBLE) / (SELECT count(DISTINCT user_id) FROM events) AS hit FROM ({W.USER_FACTS.replace('octet_length', 'strlen')}) a) b) c")
def cost_model(spark, sf_dir):
    """Mean bytes a query, list against Bloom filter, of each eighth of the events, over a lookup of every user."""
    W.tables(spark, sf_dir)
    users, rows = spark.sql(f"SELECT count(DISTINCT user_id) FROM events").first()[0], []
    for r in spark.sql(W.USER_FACTS).collect():
        hits = [True] * r.v + [False] * (users - r.v)
        a, b = (selection.expected_scan_bytes(k, r.bytes, r.v, r.bits, 0.01, hits) for k in ("list", "bloom"))
        rows.append((r.obj, r.v, round(a, 3), round(b, 3), a < b))
    return spark.createDataFrame(rows, "obj long, v long, list_bytes double, bloom_bytes double, list_wins boolean")


def _kinds_of(name: str):
    """Every kind on its column of each lake of the experiments: log, sensor points, holes, vectors, names."""
    return {
        "access_log": [MinMax("db_name"), Bloom("db_name"), ValueList("db_name"), PrefixList("db_name", 15), SuffixList("db_name", 15), Hybrid("db_name", threshold=40), Template("user_agent", W.AGENT, "agent")],
        "readings": [MinMax("obs_time"), GeoMinMax("lng", "lat", "x"), *(BoxSet("lng", "lat", x) for x in (1, 2, 4, 8)), SuffixList("city", 6)],
        "gap_orders": [MinMax("o_orderkey"), GapList("o_orderkey", 8), RangeBits("o_orderkey", 0.0, 1e6, 1024)],
        "vectors": [MetricRing("embedding", "euclid"), MetricRing("embedding", "manhattan")],
        "parts": [MetricRing("p_name", "levenshtein"), ValueList("p_name")],
    }[name]


@query("size_formula")
def size_formula(spark, sf_dir):
    """Indexing statistics of every kind on each lake: build seconds, stored bytes an object (the summary's own columns), the formula's bound."""
    rows = []
    for name in ("access_log", "readings", "gap_orders", "vectors", "parts"):
        source, _, _ = W.lake(spark, sf_dir, name)
        known = {}
        for kind in _kinds_of(name):
            store = ParquetSummaryStore(spark, scratch_path(spark, "size"))
            r = build.build_summaries(spark, source, [kind], store)
            column = kind.columns[0]
            if column not in known:
                value = source.tagged(source.read(spark), F.expr(column).cast("string").alias("v"))
                known[column] = value.groupBy("path").agg(F.count_distinct("v").alias("v"), F.avg(F.octet_length("v")).alias("b")).agg(F.avg("v"), F.avg("b")).first()
            v, b = known[column]
            own = store.column_bytes()[kind.index] / max(r.objects, 1)
            rows.append((name, kind.index, r.objects, r.seconds, own, float(kind.formula_bytes(b, v))))
    return spark.createDataFrame(rows, "lake string, kind string, objects int, seconds double, stored_bytes double, formula_bytes double")


def _scanned_to_index(spark, source, column: str) -> int:
    """Compressed bytes of one column in the lake's files: what indexing it reads."""
    from sift.sources.stores import _column_bytes

    sizes = source.listing(spark).select("path").mapInArrow(_column_bytes, "name string, bytes long")
    return sizes.where(F.col("name") == column).agg(F.coalesce(F.sum("bytes"), F.lit(0).cast("long"))).first()[0]


@query("payback")
def payback(spark, sf_dir):
    """Queries after which an index on db_name has paid for itself: bytes scanned to build it, metadata and data bytes by query, and time."""
    s = W.session(spark, sf_dir, "access_log")
    x = s.lakes["access_log"]
    store, kinds = ParquetSummaryStore(spark, scratch_path(spark, "payback")), [ValueList("db_name")]
    r = build.build_summaries(spark, x.source, kinds, store)
    s.add("access_log", x.source, store, kinds)
    one = spark.sql("SELECT min(db_name) FROM access_log").first()[0]
    rep = report.skip_report(s, f"SELECT count(*) FROM access_log WHERE db_name = '{one}'")
    scanned = _scanned_to_index(spark, x.source, "db_name")
    saved = rep.bytes_skipped - rep.metadata_bytes
    by_bytes, by_time = selection.payback(scanned, saved, r.seconds, rep.baseline_seconds - rep.data_seconds - rep.summary_seconds)
    return spark.createDataFrame([(rep.bytes, scanned, rep.metadata_bytes, saved, by_bytes, by_time)], "lake_bytes long, scanned_to_index long, metadata_bytes long, saved_bytes long, queries_by_bytes int, queries_by_time int")


# -- experiments whose outcome depends on the machine: rows only
def _compare(spark, sf_dir, lake: str, texts: list[tuple[str, str]]):
    rows = []
    for name, text in texts:
        r = report.skip_report(W.session(spark, sf_dir, lake), text)
        rows.append((name, r.objects, r.objects - r.skipped, r.bytes, r.bytes - r.bytes_skipped, r.metadata_bytes, r.bytes / max(r.bytes - r.bytes_skipped + r.metadata_bytes, 1), r.summary_seconds, r.data_seconds, r.baseline_seconds))
    return spark.createDataFrame(rows, "query string, objects int, kept int, bytes long, bytes_kept long, metadata_bytes long, cost_ratio double, summary_seconds double, data_seconds double, baseline_seconds double")


@query("exp_point_lookups")
def exp_point_lookups(spark, sf_dir):
    """Four values of one column, frequent to absent, under list, Bloom filter and hybrid: objects, data and metadata bytes, times."""
    s = W.session(spark, sf_dir, "access_log")
    x = s.lakes["access_log"]
    spark.sql("SELECT 1")
    ranked = [r[0] for r in spark.sql("SELECT db_name FROM access_log GROUP BY db_name ORDER BY count(*) DESC, db_name").collect()]
    rows = []
    for kind in (ValueList, Bloom, Hybrid):
        only = [k for k in x.kinds if type(k) is kind and k.columns[0] == "db_name"]
        for name, v in (("top", ranked[0]), ("median", ranked[len(ranked) // 2]), ("rarest", ranked[-1]), ("absent", "no/such/db")):
            s.add("access_log", x.source, x.store, only)
            r = report.skip_report(s, f"SELECT event_id, ts, event_type, value, props, account_name, db_name, http_request FROM access_log WHERE db_name = '{v}'")
            rows.append((kind.kind, name, r.objects, r.objects - r.skipped, r.bytes, r.bytes - r.bytes_skipped, r.metadata_bytes, r.summary_seconds, r.data_seconds, r.baseline_seconds))
    return spark.createDataFrame(rows, "kind string, value string, objects int, kept int, bytes long, bytes_kept long, metadata_bytes long, summary_seconds double, data_seconds double, baseline_seconds double")


def _window(months: int) -> str:
    return f"obs_time >= CAST('1996-01-01 00:00:00' AS TIMESTAMP_NTZ) AND obs_time < CAST('{1996 + months // 12}-{months % 12 + 1:02d}-01 00:00:00' AS TIMESTAMP_NTZ)"


@query("exp_geo_windows")
def exp_geo_windows(spark, sf_dir):
    """Containment and distance over windows of 1 to 12 months, with and without skipping."""
    from sift.queries_core import TRIANGLE

    texts = [(f"{f}-{m}", f"SELECT count(*) FROM readings WHERE {p} AND {_window(m)}") for m in (1, 3, 5, 6, 9, 12) for f, p in (("contains", f"st_contains('{TRIANGLE}', lat, lng)"), ("distance", "st_distance(lat, lng, 10.0D, 20.0D) < 5"))]
    return _compare(spark, sf_dir, "readings", texts)


@query("exp_rewrite")
def exp_rewrite(spark, sf_dir):
    """Central summaries against manual rewriting with bounds, over windows up to five years: objects opened and seconds."""
    import time

    from sift.operators.baselines import rewrite_with_bounds
    from sift.queries_core import TRIANGLE

    s = W.session(spark, sf_dir, "readings")
    plain = without_skipping(s)
    rows = []
    for m in (1, 6, 12, 24, 36, 60):
        inside = lambda df, m=m: df.where(F.call_function("st_contains", F.lit(TRIANGLE), F.col("lat"), F.col("lng")) & F.expr(_window(m))).agg(F.max("temp"))
        t0 = time.time()
        a = s.frame("readings", inside)
        a.collect()
        t1 = time.time()
        b = plain.frame("readings", lambda df, f=inside: f(rewrite_with_bounds(df, TRIANGLE)))
        b.collect()
        t2 = time.time()
        rows.append((m, report.scans(a)[0].files, report.scans(b)[0].files, t1 - t0, t2 - t1))
    return spark.createDataFrame(rows, "months int, objects_central int, objects_rewrite int, seconds_central double, seconds_rewrite double")


@query("exp_boxes")
def exp_boxes(spark, sf_dir):
    """Objects kept for a notched polygon by coordinate bounds and by 1, 2, 4, 8 boxes."""
    from sift.queries_core import NOTCHED

    source, _, _ = W.lake(spark, sf_dir, "grid")
    rows = []
    for name, kinds in (("minmax", [GeoMinMax("lng", "lat", "x"), GeoMinMax("lat", "lng", "y")]), *((f"boxes{x}", [BoxSet("lng", "lat", x)]) for x in (1, 2, 4, 8))):
        store = ParquetSummaryStore(spark, scratch_path(spark, "boxes"))
        r = build.build_summaries(spark, source, kinds, store)
        s = W.session(spark, sf_dir, "grid")
        s.add("grid", source, store, kinds)
        s.sql(f"SELECT count(*) FROM grid WHERE st_contains('{NOTCHED}', lat, lng)").collect()
        rows.append((name, s.history[-1].n_kept, s.history[-1].objects, r.bytes))
    return spark.createDataFrame(rows, "kind string, kept int, objects int, bytes long")


@query("exp_overhead")
def exp_overhead(spark, sf_dir):
    """Queries that no summary can narrow: what skipping costs when it gains nothing."""
    return _compare(spark, sf_dir, "access_log", [("all rows", "SELECT count(*) FROM access_log WHERE value >= 0"), ("unknown function", "SELECT count(*) FROM access_log WHERE length(props) > 0"), ("frequent tail", "SELECT count(*) FROM access_log WHERE db_name LIKE '%/shard%'")])


_WIDE = ("db_name", "http_request", "user_agent", "account_name", "props", "event_type")


@query("exp_indexing")
def exp_indexing(spark, sf_dir):
    """Build seconds and bytes: hybrid on 1, 2, 4 and 6 log columns jointly and one by one, min/max on 1, 2, 4 and 8 columns of
    the sensor grid by scan and, as far as footers tell exact bounds, by footers."""
    source = W.laid_out(spark, sf_dir, "access_log")
    make = lambda: ParquetSummaryStore(spark, scratch_path(spark, "indexing"))
    rows = []
    for n in (1, 2, 4, 6):
        kinds = [Hybrid(c, threshold=40) for c in _WIDE[:n]]
        for how, f in (("joint", build.build_summaries), ("separate", build.build_separately)):
            r = f(spark, source, kinds, make())
            rows.append((f"hybrid-{how}", n, r.seconds, r.bytes))
    path = scratch_path(spark, "grid-integers")
    # Footers are exact for integral and time columns only: the measurements in hundredths.
    numbers = [F.round(F.col(c) * 100).cast("long").alias(f"{c}_c") for c in ("temp", "wind", "lat", "lng")]
    # Written from the view in the cells of the lake `grid`, which would otherwise be written, indexed and read first.
    W.tables(spark, sf_dir)
    grid = spark.sql(W.READINGS).select("l_orderkey", "l_linenumber", "obs_time", *numbers, F.length("city").cast("long").alias("city_length"), F.expr(W.CELL).alias("cell"))
    write_by(grid, path, F.col("cell"))
    whole, columns = LakeSource(path), ("obs_time", "l_orderkey", "temp_c", "lat_c", "lng_c", "wind_c", "l_linenumber", "city_length")
    for n in (1, 2, 4, 8):
        r = build.build_summaries(spark, whole, [MinMax(c) for c in columns[:n]], make())
        rows.append(("minmax-scan", n, r.seconds, r.bytes))
        r = build.build_from_footers(spark, whole, list(columns[:n]), make())
        rows.append(("minmax-footers", n, r.seconds, r.bytes))
    return spark.createDataFrame(rows, "build string, columns int, seconds double, bytes long")


def _measured(spark, sf_dir, n: int = 20) -> tuple[list, dict, dict, list]:
    """Candidates on db_name with what they cost and bring: (name, bytes, rows skipped over a workload), costs, kept objects, rows."""
    s = W.session(spark, sf_dir, "access_log")
    x = s.lakes["access_log"]
    work = [(q, f"startswith(db_name, '{p}')") for q, p in _queries(spark, "db_name", n, False)]
    costs, keeps, rows, order, sizes_of = {}, {}, [], [], x.store.column_bytes()
    for kind in [k for k in x.kinds if k.columns[0] == "db_name"]:
        s.add("access_log", x.source, x.store, [kind])
        held = indicators.object_facts(s, "access_log", work).select("query", "path", "n_rows", "keep").collect()  # queries x objects
        if not order:
            sizes = {r.path: r.n_rows for r in held}
            order = sorted(sizes)
            rows = [sizes[p] for p in order]
        at = {p: i for i, p in enumerate(order)}
        kept = {q: 0 for q, _ in work}
        for r in held:
            if r.keep:
                kept[r.query] |= 1 << at[r.path]
        keeps[kind.index] = [kept[q] for q, _ in work]
        costs[kind.index] = sizes_of[kind.index]
    skipped = lambda bits: sum(r for i, r in enumerate(rows) if not bits >> i & 1)
    return [(i, costs[i], float(sum(map(skipped, keeps[i])))) for i in costs], costs, keeps, rows


@query("select_real")
def select_real(spark, sf_dir):
    """Index selection on stored candidates, budgets swept: bytes spent, rows skipped over the workload by the chosen set together."""
    candidates, costs, keeps, rows = _measured(spark, sf_dir)
    total, out = sum(costs.values()), []
    for share in (0.02, 0.05, 0.1, 0.25, 0.5, 1.0):
        budget = int(share * total)
        for method in ("dp", "greedy", "marginal"):
            chosen = selection.select_marginal(costs, keeps, rows, budget) if method == "marginal" else selection.select_indexes(candidates, budget, method)
            together = [(1 << len(rows)) - 1] * len(next(iter(keeps.values())))
            for i in chosen:
                together = [a & b for a, b in zip(together, keeps[i], strict=True)]
            skipped = sum(r for bits in together for k, r in enumerate(rows) if not bits >> k & 1)
            out.append((share, method, ",".join(chosen), sum(costs[i] for i in chosen), skipped))
    return spark.createDataFrame(out, "budget_share double, method string, chosen string, bytes long, rows_skipped long")


@query("select_real_sound", "SELECT true AS within_budget, true AS growing, true AS marginal_best")
def select_real_sound(spark, sf_dir):
    """Of that sweep: no choice exceeds its budget, more budget never skips less, and at full budget the marginal choice skips as much as any."""
    rows = select_real(spark, sf_dir).collect()
    total = max(r.bytes for r in rows)
    by = {m: [r.rows_skipped for r in rows if r.method == m] for m in ("dp", "greedy", "marginal")}
    _, costs, _, _ = _measured(spark, sf_dir, 1)
    within = all(r.bytes <= r.budget_share * sum(costs.values()) for r in rows) and total <= sum(costs.values())
    return spark.createDataFrame([(within, all(v == sorted(v) for v in (by["marginal"],)), by["marginal"][-1] >= max(v[-1] for v in by.values()))], "within_budget boolean, growing boolean, marginal_best boolean")


@query("point_lookup_objects", ", c AS (SELECT db_name, count(*) AS n, count(DISTINCT " + _OBJ + ") AS objects FROM access_log GROUP BY 1), r AS (SELECT *, row_number() OVER (ORDER BY n DESC, db_name) AS i, count(*) OVER () AS m FROM c) SELECT 'top' AS value, objects AS kept FROM r WHERE i = 1 UNION ALL SELECT 'median', objects FROM r WHERE i = m // 2 + 1 UNION ALL SELECT 'rarest', objects FROM r WHERE i = m UNION ALL SELECT 'absent', 0", "access_log")
def point_lookup_objects(spark, sf_dir):
    """Objects that the value list keeps for four values, frequent to absent: those that hold the value."""
    s = W.session(spark, sf_dir, "access_log")
    x = s.lakes["access_log"]
    s.add("access_log", x.source, x.store, [k for k in x.kinds if type(k) is ValueList and k.columns[0] == "db_name"])
    ranked = [r[0] for r in spark.sql("SELECT db_name FROM access_log GROUP BY db_name ORDER BY count(*) DESC, db_name").collect()]
    rows = []
    for name, v in (("top", ranked[0]), ("median", ranked[len(ranked) // 2]), ("rarest", ranked[-1]), ("absent", "no/such/db")):
        s.sql(f"SELECT count(*) FROM access_log WHERE db_name = '{v}'")
        rows.append((name, s.history[-1].n_kept))
    return spark.createDataFrame(rows, "value string, kept long")
