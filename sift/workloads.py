"""The data sets and query sets of the experiments, derived from the given tables."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sift.operators.build import build_summaries
from sift.operators.kinds import Bloom, BoxSet, GapList, GeoMinMax, Hybrid, MetricRing, MinMax, PrefixList, SuffixList, SummaryKind, Template, ValueList
from sift.runtime import scratch_path, table
from sift.session import SiftSession
from sift.sources.lake import LakeSource
from sift.sources.layouts import layout_kdtree, layout_random, write_by
from sift.sources.stores import ParquetSummaryStore, SummaryStore

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

#: Views over the given tables, in SQL that Spark and DuckDB both run.
READINGS = """SELECT l_orderkey, l_linenumber, l_shipdate AS obs_time, l_extendedprice/1000 AS temp, l_quantity AS wind,
  CAST((l_partkey*7919 + l_suppkey*104729) % 18001 AS DOUBLE)/100 - 90 AS lat,
  CAST((l_orderkey*15485863 + l_linenumber*32452843) % 36001 AS DOUBLE)/100 - 180 AS lng,
  p_name || ' ' || n_name AS city
FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey"""
ACCESS_LOG = """SELECT e.event_id, e.ts, CAST(e.ts AS DATE) AS day, e.event_type, e.value, e.props, e.user_id,
  'acct_' || CAST(e.user_id AS VARCHAR(12)) AS account_name,
  regexp_extract(d.url,'^https?://([^/]+)',1) || '/db' || CAST(e.user_id AS VARCHAR(12)) || '/shard'
    || CAST(CAST(regexp_extract(e.props,'([0-9]+)',1) AS INT) % 10 AS VARCHAR(12)) AS db_name,
  p.url AS http_request,
  CASE WHEN e.event_id % 499 = 13 THEN 'probe-bot' ELSE 'agent' || CAST(e.user_id % 37 AS VARCHAR(12)) END
    || '/' || CAST(e.event_id % 9 AS VARCHAR(12)) || '.0 (' || e.event_type || ')' AS user_agent
FROM events e CROSS JOIN (SELECT count(*) AS n_pages FROM pages) c
  JOIN pages p ON p.page_id = e.event_id % c.n_pages JOIN pages d ON d.page_id = e.user_id % c.n_pages"""
GAPPED = "SELECT * FROM orders WHERE o_orderkey % 1000 < 600"

AGENT = r"regexp_extract(user_agent, '^([^/]+)', 1)"
HOST = r"regexp_extract(url, '^https?://([^/]+)', 1)"
JSON_K = "get_json_object(props, '$.k')"

#: Bytes, distinct users and a user's mean bits, as text, of each eighth of the events; DuckDB's octet_length is strlen.
USER_FACTS = """SELECT obj, CAST(sum(n) AS BIGINT) AS bytes, CAST(count(DISTINCT who) AS BIGINT) AS v, CAST(8 * sum(octet_length(who)) AS DOUBLE) / CAST(count(who) AS DOUBLE) AS bits
FROM (SELECT event_id % 8 AS obj, 24 + coalesce(octet_length(event_type), 0) + coalesce(octet_length(props), 0) AS n, CAST(user_id AS VARCHAR(12)) AS who FROM events) p GROUP BY obj HAVING count(who) > 0"""


@dataclass(frozen=True)
class LakeSpec:
    """A lake: the view it holds (SQL), how it is dealt to objects, its kinds, and the object's logical id in SQL."""

    sql: str
    write: Callable[[DataFrame, str], None]
    kinds: Callable[[], list[SummaryKind]]
    obj: str = ""
    fmt: str = "parquet"


def _by(obj: str) -> Callable[[DataFrame, str], None]:
    return lambda df, path: write_by(df, path, F.expr(obj))


DAY = "date_format(ts, 'yyyy-MM-dd')"
MONTH = "date_format(o_orderdate, 'yyyy-MM')"
CELL = "concat_ws('-', cast(floor((lat+90)/45) as string), cast(floor((lng+180)/45) as string))"

LAKES: dict[str, LakeSpec] = {
    "ev": LakeSpec("SELECT * FROM events", _by(DAY), lambda: [MinMax("value"), MinMax("ts"), MinMax("event_id"), ValueList("event_type"), Bloom("user_id"), Template("props", JSON_K, "k"), MinMax("user_id")]),
    "od": LakeSpec("SELECT * FROM orders", _by(MONTH), lambda: [MinMax("o_orderdate"), MinMax("o_totalprice"), MinMax("o_orderkey"), ValueList("o_orderstatus"), ValueList("o_orderpriority"), MinMax("o_orderpriority"), Bloom("o_custkey")]),
    "li": LakeSpec("SELECT * FROM lineitem", _by("date_format(l_shipdate, 'yyyy-MM')"), lambda: [MinMax("l_shipdate"), MinMax("l_quantity"), MinMax("l_discount"), MinMax("l_orderkey"), Bloom("l_partkey"), ValueList("l_returnflag")]),
    "gap_orders": LakeSpec(GAPPED, _by("cast(o_orderkey div 5000 as string)"), lambda: [MinMax("o_orderkey"), GapList("o_orderkey", 8)]),
    "readings": LakeSpec(READINGS, lambda df, path: layout_kdtree(df, path, ["lng", "lat"], 16, F.year("obs_time")), lambda: [GeoMinMax("lng", "lat", "x"), GeoMinMax("lat", "lng", "y"), BoxSet("lng", "lat", 1), BoxSet("lng", "lat", 4), MinMax("obs_time"), SuffixList("city", 6), MinMax("temp")]),
    "grid": LakeSpec(READINGS, _by(CELL), lambda: [BoxSet("lng", "lat", 1), GeoMinMax("lng", "lat", "x"), GeoMinMax("lat", "lng", "y")]),
    "access_log": LakeSpec(ACCESS_LOG, _by(f"concat_ws('-', {DAY}, cast(user_id % 4 as string))"), lambda: [Hybrid("db_name", threshold=40), Bloom("db_name"), ValueList("db_name"), PrefixList("db_name", 15), SuffixList("db_name", 15), PrefixList("http_request", 20), Template("user_agent", AGENT, "agent"), MinMax("day"), MinMax("db_name"), MinMax("value"), ValueList("event_type")]),
    "hourly_log": LakeSpec(ACCESS_LOG, _by("concat(date_format(ts, 'yyyy-MM-dd-'), cast(hour(ts) div 3 as string))"), lambda: [Template("user_agent", AGENT, "agent"), MinMax("ts")]),
    "vectors": LakeSpec("SELECT * FROM embeddings", _by("cast(label as string)"), lambda: [MetricRing("embedding", "euclid"), MetricRing("embedding", "manhattan"), MinMax("label")]),
    "parts": LakeSpec("SELECT * FROM part", _by("p_brand"), lambda: [MetricRing("p_name", "levenshtein"), ValueList("p_name"), MinMax("p_partkey")]),
    "texts": LakeSpec("SELECT d.doc_id, d.text, d.lang, d.source, d.n_chars FROM documents d", _by("concat_ws('-', lang, source)"), lambda: [ValueList("split(text, ' ')", elements=True), ValueList("lang"), MinMax("n_chars")]),
    "web": LakeSpec("SELECT * FROM pages", _by("cast(page_id % 8 as string)"), lambda: [Template("url", HOST, "host"), Template("url", r"regexp_extract(url, '[?&]ref=([^&#]*)', 1)", "ref"), Template("html", r"""regexp_extract(html, 'lang="([a-z]+)"', 1)""", "lang"), MinMax("page_id")]),
}

_ready: dict[tuple, SiftSession] = {}
_laid_out: dict[tuple, LakeSource] = {}
_lakes: dict[tuple, tuple[LakeSource, SummaryStore, list[SummaryKind]]] = {}


def tables(spark: SparkSession, sf_dir: str) -> None:
    """The given tables as views."""
    for t in TABLES:
        table(spark, sf_dir, t).createOrReplaceTempView(t)


def laid_out(spark: SparkSession, sf_dir: str, name: str) -> LakeSource:
    """A lake laid out, whether it is indexed or not; once for a session and a directory."""
    k = (spark.sparkContext.applicationId, sf_dir, name)
    if k not in _laid_out:
        spec = LAKES[name]
        tables(spark, sf_dir)
        path = scratch_path(spark, f"lake-{name}")
        spec.write(spark.sql(spec.sql), path)
        _laid_out[k] = LakeSource(path)
    return _laid_out[k]


def lake(spark: SparkSession, sf_dir: str, name: str) -> tuple[LakeSource, SummaryStore, list[SummaryKind]]:
    """A lake laid out and indexed; once for a session and a directory."""
    k = (spark.sparkContext.applicationId, sf_dir, name)
    if k not in _lakes:
        source = laid_out(spark, sf_dir, name)
        store, kinds = ParquetSummaryStore(spark, scratch_path(spark, f"store-{name}")), LAKES[name].kinds()
        build_summaries(spark, source, kinds, store)
        _lakes[k] = source, store, kinds
    return _lakes[k]


def session(spark: SparkSession, sf_dir: str, *names: str, skipping: bool = True) -> SiftSession:
    """A session over some of the lakes, with the given tables as views too."""
    tables(spark, sf_dir)
    s = SiftSession(spark, skipping=skipping)
    for n in names:
        s.add(n, *lake(spark, sf_dir, n))
    return s


def oracle_views(*names: str) -> str:
    """The lakes' views as a WITH clause for DuckDB."""
    return "WITH " + ", ".join(f"{n} AS ({LAKES[n].sql})" for n in names) + " " if names else ""


# -- query sets


def polygon(cx: float, cy: float, size: float, concave: bool = False) -> str:
    """A small triangle around a point, or one with a notch."""
    pts = [(cx - size, cy - size), (cx + size, cy - size), (cx, cy + size)]
    if concave:
        pts.insert(1, (cx, cy - size / 4))
    pts.append(pts[0])
    return "POLYGON((" + ", ".join(f"{x} {y}" for x, y in pts) + "))"
