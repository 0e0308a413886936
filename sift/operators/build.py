"""Building and refreshing summaries.

All aggregate kinds share one scan and one exchange: partial aggregates by object are built where the data are read, and
only they travel. Kinds with a second pass scan their own columns again. Objects without rows appear through the listing.
"""

from __future__ import annotations

import time
from collections.abc import Iterable
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sift.operators.kinds import MinMax, SummaryKind, Template, ValueList
from sift.plans import bridge
from sift.runtime import materialise, ship_package
from sift.sources.lake import LakeSource, among, digest
from sift.sources.stores import SummaryStore


@dataclass
class BuildReport:
    """What a build did; ``bytes`` is the store's size after it."""

    indexes: list[str]
    objects: int
    seconds: float
    bytes: int


def _columns(kind: SummaryKind, k: int) -> list:
    return [c.alias(f"k{k}_{i}") for i, c in enumerate(kind.inputs())]


def summary_rows(df: DataFrame, source: LakeSource, kinds: list[SummaryKind]) -> DataFrame:
    """(path, mtime, size, n_rows, a struct for each kind) of the objects that have rows in ``df``."""
    inputs = [c for k, kind in enumerate(kinds) for c in _columns(kind, k)]
    rows = source.tagged(df, *inputs)
    aggs = []
    for k, kind in enumerate(kinds):
        own = [f"k{k}_{i}" for i in range(len(kind.inputs()))]
        whole = F.col(own[0]).isNotNull()
        for c in own[1:]:
            whole = whole & F.col(c).isNotNull()
        fields = kind.aggregates(*map(F.col, own))
        at = [F.count(F.when(whole, 1)).alias("n_nonnull"), *(f.alias(n) for n, f in fields.items())]
        aggs.append(F.struct(*at).alias(f"f{k}"))
    grouped = rows.groupBy("path", "mtime", "size").agg(F.count("*").alias("n_rows"), *aggs)
    second = [k for k, kind in enumerate(kinds) if kind.passes() == 2]
    if second:
        grouped = materialise(grouped, "summaries")
    out = grouped.select("path", "mtime", "size", "n_rows", *(_finished(kind, k) for k, kind in enumerate(kinds) if k not in second))
    for k in second:
        extra = kinds[k].second_pass(*_pass_inputs(rows, grouped, kinds, k))
        if len(second) > 1:  # each planned by itself: the driver holds one plan at a time, however many kinds there are
            extra = materialise(extra, "second")
        out = out.join(extra, "path", "left")
    return out.select("path", "mtime", "size", "n_rows", *(kind.index for kind in kinds))


def _pass_inputs(rows: DataFrame, grouped: DataFrame, kinds: list[SummaryKind], k: int) -> tuple[DataFrame, DataFrame]:
    n = len(kinds[k].inputs())
    return rows.select("path", *(F.col(f"k{k}_{i}").alias(f"c{i}") for i in range(n))), grouped.select("path", f"f{k}.*")


def _finished(kind: SummaryKind, k: int):
    names = list(kind.aggregates(*(F.col(f"k{k}_{i}") for i in range(len(kind.inputs())))))
    fields = kind.finish({n: F.col(f"f{k}.{n}") for n in names})
    return F.struct(F.col(f"f{k}.n_nonnull").alias("n_nonnull"), *(c.alias(n) for n, c in fields.items())).alias(kind.index)


def bind(kinds: Iterable[SummaryKind], source: LakeSource, spark: SparkSession) -> list[SummaryKind]:
    """Let kinds over extracted values know how their extractor looks in Spark's plans."""
    kinds = list(kinds)
    for k in kinds:
        if k.signature is None and (isinstance(k, Template) or isinstance(k, ValueList) and k.params["elements"]):
            text = k.params["extractor"] if isinstance(k, Template) else k.columns[0]
            probe = f"({text}) = 'x'" if isinstance(k, Template) else f"array_contains({text}, 'x')"
            use = bridge.relations(source.read(spark).where(probe))
            leaf = [n for n in use[0].predicate.walk() if n.kind in ("cmp", "member")] if use else []
            k.signature = leaf[0].term if leaf else None
    return kinds


def build_summaries(spark: SparkSession, source: LakeSource, kinds: list[SummaryKind], store: SummaryStore, *, mode: str = "replace", only: DataFrame | None = None) -> BuildReport:
    """Build all ``kinds`` of a data set together and commit them to ``store``; ``only`` (path) limits it to some objects."""
    began = time.time()
    kinds = list({k.index: k for k in kinds}.values())  # kinds that differ in what they match share a summary
    df, listed = source.read(spark), source.listing(spark)
    if only is not None:
        chosen = [r.d for r in only.select(digest(F.col("path")).alias("d")).collect()]  # 16 bytes an object
        df = df.where(among(F.col("_metadata.file_path"), chosen, True))
        listed = listed.join(only, "path", "left_semi")
    rows = summary_rows(df, source, bind(kinds, source, spark))
    whole = listed.join(rows, ["path", "mtime", "size"], "left").withColumn("n_rows", F.coalesce("n_rows", F.lit(0)).cast("long"))
    store.write(whole, kinds, mode=mode)
    return BuildReport([k.index for k in kinds], store.objects(), time.time() - began, store.bytes())


def build_separately(spark: SparkSession, source: LakeSource, kinds: list[SummaryKind], store: SummaryStore) -> BuildReport:
    """Baseline: one scan for each kind, their rows joined afterwards."""
    began = time.time()
    whole = source.listing(spark)
    counted = None
    for kind in bind(kinds, source, spark):
        rows = materialise(summary_rows(source.read(spark), source, [kind]), "separate")
        counted = rows.select("path", "n_rows") if counted is None else counted
        whole = whole.join(rows.drop("n_rows"), ["path", "mtime", "size"], "left")
    whole = whole.join(counted, "path", "left").withColumn("n_rows", F.coalesce("n_rows", F.lit(0)).cast("long"))
    store.write(whole, kinds)
    return BuildReport([k.index for k in kinds], store.objects(), time.time() - began, store.bytes())


#: Parquet footers tell exact bounds of these types; floating and string bounds may be inexact or cut.
FOOTER_TYPES = ("tinyint", "smallint", "int", "bigint", "date", "timestamp_ntz", "timestamp")


def build_from_footers(spark: SparkSession, source: LakeSource, columns: list[str], store: SummaryStore) -> BuildReport:
    """Min/max of integral and time columns of Parquet files from their footers, without reading any row."""
    began = time.time()
    types = {f.name: f.dataType for f in source.read(spark).schema if f.name in columns}
    if source.fmt != "parquet" or source.derive or any(t.simpleString() not in FOOTER_TYPES for t in types.values()):
        raise ValueError("footers serve stored integral and time columns of Parquet files only")
    ship_package(spark)
    listed = source.listing(spark)
    n = max(1, min(200, listed.count() // 64))
    fields = ", ".join(f"n{i} long, lo{i} long, hi{i} long" for i in range(len(columns)))
    read = listed.repartition(n, "path").mapInArrow(_footers(columns), f"path string, mtime long, size long, n_rows long, {fields}")

    def value(c, t):
        return F.expr(f"timestampadd(MICROSECOND, {c}, timestamp_ntz'1970-01-01 00:00:00')") if t.simpleString() == "timestamp_ntz" else F.timestamp_micros(F.col(c)) if t.simpleString() == "timestamp" else F.date_from_unix_date(F.col(c).cast("int")) if t.simpleString() == "date" else F.col(c).cast(t)

    kinds = [MinMax(c) for c in columns]
    rows = read.select("path", "mtime", "size", "n_rows", *(F.struct(F.col(f"n{i}").alias("n_nonnull"), value(f"lo{i}", types[c]).alias("lo"), value(f"hi{i}", types[c]).alias("hi")).alias(k.index) for i, (c, k) in enumerate(zip(columns, kinds, strict=True))))
    store.write(rows, kinds)
    return BuildReport([k.index for k in kinds], store.objects(), time.time() - began, store.bytes())


def _footers(columns: list[str]):
    def whole(v) -> int | None:
        import datetime as dt

        if isinstance(v, dt.datetime):
            return (v.replace(tzinfo=None) - dt.datetime(1970, 1, 1)) // dt.timedelta(microseconds=1)
        return (v - dt.date(1970, 1, 1)).days if isinstance(v, dt.date) else v

    def run(batches):
        import pyarrow.parquet as pq
        from pyarrow import fs
        from urllib.parse import unquote

        for batch in batches:
            out = []
            for path, mtime, size in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                where = unquote(path)
                system, inner = (fs.LocalFileSystem(), where.removeprefix("file://").removeprefix("file:")) if where.startswith("file:") else fs.FileSystem.from_uri(where)
                with system.open_input_file(inner) as f:
                    meta = pq.ParquetFile(f).metadata
                row = [path, mtime, size, meta.num_rows]
                for c in columns:
                    lo, hi, nonnull, sure = None, None, 0, True
                    for g in range(meta.num_row_groups):
                        group = meta.row_group(g)
                        stats = next(group.column(j).statistics for j in range(group.num_columns) if group.column(j).path_in_schema == c)
                        if stats is None or not stats.has_null_count or stats.num_values and not stats.has_min_max:
                            sure = False
                            break
                        nonnull += stats.num_values
                        if stats.num_values:
                            a, b = whole(stats.min), whole(stats.max)
                            lo, hi = a if lo is None else min(lo, a), b if hi is None else max(hi, b)
                    row += [nonnull, lo, hi] if sure else [None, None, None]
                out.append(row)
            cols = list(zip(*out, strict=True))
            names = ["path", "mtime", "size", "n_rows", *(f"{a}{i}" for i in range(len(columns)) for a in ("n", "lo", "hi"))]
            if cols:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.string() if n == "path" else pa.int64()) for c, n in zip(cols, names, strict=True)], names)

    return run


@dataclass
class RefreshReport:
    added: int
    rebuilt: int
    dropped: int
    untouched: int


def refresh_summaries(spark: SparkSession, source: LakeSource, kinds: list[SummaryKind], store: SummaryStore) -> RefreshReport:
    """Bring a store up to date: build what is new or was overwritten, drop what is gone, touch nothing else."""
    known = store.rows([]).select("path", F.col("mtime").alias("m"), F.col("size").alias("s"))
    state = source.listing(spark).join(known, "path", "full_outer").select("path", F.when(F.col("m").isNull(), "added").when(F.col("mtime").isNull(), "dropped").when((F.col("m") != F.col("mtime")) | (F.col("s") != F.col("size")), "rebuilt").otherwise("untouched").alias("state"))
    state = materialise(state, "refresh")
    n = {r.state: r["count"] for r in state.groupBy("state").count().collect()}
    if n.get("dropped"):
        store.drop_objects(materialise(state.where("state = 'dropped'").select("path"), "gone"), kinds)
    if n.get("added") or n.get("rebuilt"):
        build_summaries(spark, source, kinds, store, mode="append", only=state.where("state IN ('added', 'rebuilt')").select("path"))
    return RefreshReport(n.get("added", 0), n.get("rebuilt", 0), n.get("dropped", 0), n.get("untouched", 0))
