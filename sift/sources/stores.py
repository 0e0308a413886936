"""Where summaries live: wide rows, one per object, one struct column per index.

Every store appends batches and commits a manifest last; a reader sees committed batches only. An index may be
encrypted under a key: without the key its column is missing and the index is not used.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterable
from functools import reduce

import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sift.plans.keep import KeepTest
from sift.runtime import ship_package

IDENTITY = ("path", "mtime", "size", "n_rows")
#: Batches from which on an append merges the newest ones, and manifests that are kept.
COMPACT_AFTER = 32
KEEP_VERSIONS = 3


def _told(description: dict) -> dict:
    """A description by which stored summaries can be told apart; whether fields may be null is no difference."""
    return description | {"type": T._parse_datatype_json_string(description["type"]).simpleString()}


class SummaryStore:
    """Common to all stores: manifest, encryption, translation and evaluation of tests."""

    def __init__(self, spark: SparkSession, path: str, keys: dict[str, bytes] | None = None):
        self.spark, self.path, self.keys = spark, path.rstrip("/"), dict(keys or {})
        self._cached: dict[frozenset, DataFrame] = {}

    # -- what a backend provides
    def _append(self, rows: DataFrame, batch: str) -> None:
        raise NotImplementedError

    def _load(self, batch: str, schema: T.StructType, needed: list[str]) -> DataFrame:
        raise NotImplementedError

    # -- manifest: a file for each version; the highest one counts
    def _fs(self, name: str = ""):
        jvm = self.spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}" if name else self.path)
        return jvm, p, p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def _versions(self) -> list[int]:
        jvm, p, fs = self._fs()
        if not fs.exists(p):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(p)]
        return sorted(int(m[1]) for n in names if (m := re.fullmatch(r"manifest-(\d+)\.json", n)))

    def manifest(self) -> dict:
        held = self._versions()
        if not held:
            return {"version": 0, "indexes": {}, "batches": []}
        jvm, p, fs = self._fs(f"manifest-{held[-1]:08d}.json")
        opened = fs.open(p)
        try:
            return json.loads(jvm.org.apache.commons.io.IOUtils.toString(opened, "UTF-8"))
        finally:
            opened.close()

    def _commit(self, manifest: dict, after: int) -> None:
        """Publish ``manifest`` as the version after ``after``; another writer's commit in between is an error, not a loss."""
        manifest = manifest | {"version": after + 1}
        jvm, p, fs = self._fs(f"manifest-{after + 1:08d}.json")
        _, tmp, _ = self._fs(f"manifest-{after + 1:08d}.json.{jvm.System.nanoTime()}")
        out = fs.create(tmp, True)
        out.write(bytearray(json.dumps(manifest).encode()))
        out.close()
        if fs.exists(p) or not fs.rename(tmp, p):
            fs.delete(tmp, False)
            raise RuntimeError(f"version {after + 1} of {self.path} was committed by another writer")
        for old in self._versions()[:-KEEP_VERSIONS]:
            fs.delete(self._fs(f"manifest-{old:08d}.json")[1], False)
        self._cached.clear()

    # -- writing
    def write(self, rows: DataFrame, kinds: Iterable, *, mode: str = "replace") -> None:
        """Add a batch of summary rows; ``replace`` makes it the only one, ``append`` keeps the older ones.

        What is appended under a name that the store has must have the same columns and parameters.
        """
        was = self.manifest()
        manifest = was if mode == "append" else {"indexes": {}, "batches": []}
        kinds, schema = list(kinds), rows.schema
        for k in kinds:
            told = json.loads(json.dumps(k.describe() | {"type": schema[k.index].dataType.json()}))
            if _told(manifest["indexes"].setdefault(k.index, told)) != _told(told):
                raise ValueError(f"{k.index} is stored with other parameters")
        out = rows
        for k in kinds:
            if k.key_id:
                key = self.keys[k.key_id]
                sealed = F.base64(F.aes_encrypt(F.to_json(F.col(k.index), {"ignoreNullFields": "false"}), F.lit(bytearray(key)), F.lit("GCM")))
                out = out.withColumn(k.index, sealed)
        manifest["batches"].append(self._add(out, [k.index for k in kinds]))
        self._commit(manifest, was["version"])
        if len(manifest["batches"]) > COMPACT_AFTER:
            self.compact()

    def _add(self, rows: DataFrame, indexes: list[str]) -> dict:
        batch = f"batch-{self.spark.sparkContext._jvm.System.nanoTime()}"
        self._append(rows, batch)
        identity = T.StructType([T.StructField("path", T.StringType())])
        return {"name": batch, "indexes": indexes, "objects": self._load(batch, identity, []).count()}

    def compact(self) -> None:
        """Merge the newest batches into one, back to a batch four times as large as all that came after it.

        So each object is rewritten a few times only, however many batches arrive. Sealed summaries stay sealed.
        """
        manifest = self.manifest()
        batches, total, first = manifest["batches"], 0, len(manifest["batches"])
        while first and (len(batches) - first < 2 or batches[first - 1]["objects"] <= 4 * total):
            first -= 1
            total += batches[first]["objects"]
        if len(batches) - first < 2:
            return
        names = sorted({i for b in batches[first:] for i in b["indexes"]})
        types = {i: T.StringType() if manifest["indexes"][i]["key_id"] else T._parse_datatype_json_string(manifest["indexes"][i]["type"]) for i in names}
        rows = self._resolved([self._read(b, types, n) for n, b in enumerate(batches[first:])])
        merged = self._add(rows.drop("batch"), names)
        self._commit(manifest | {"batches": [*batches[:first], merged]}, manifest["version"])

    def objects(self) -> int:
        """Summary rows in all batches: at least the number of indexed objects."""
        return sum(b["objects"] for b in self.manifest()["batches"])

    # -- reading
    def indexes(self) -> dict[str, dict]:
        """Indexes that this user can read."""
        return {i: d for i, d in self.manifest()["indexes"].items() if not d["key_id"] or d["key_id"] in self.keys}

    def hidden(self) -> list[str]:
        """Indexes that need a key which isn't here."""
        return sorted(set(self.manifest()["indexes"]) - set(self.indexes()))

    def _read(self, batch: dict, types: dict, number: int) -> DataFrame:
        """Identity columns and the summaries in ``types`` of one batch, null where it has none."""
        own = [T.StructField(i, t) for i, t in types.items() if i in batch["indexes"]]
        schema = T.StructType([T.StructField("path", T.StringType()), *(T.StructField(c, T.LongType()) for c in IDENTITY[1:]), *own])
        df = self._load(batch["name"], schema, [f.name for f in own])
        return df.select(*IDENTITY, *(F.col(i) if i in batch["indexes"] else F.lit(None).cast(t).alias(i) for i, t in types.items()), F.lit(number).alias("batch"))

    @staticmethod
    def _resolved(parts: list[DataFrame]) -> DataFrame:
        """All rows, of an object indexed more than once those of the newest batch. Only paths travel to find the older ones."""
        out = reduce(DataFrame.unionByName, parts)
        if len(parts) == 1:
            return out
        at = reduce(DataFrame.union, (p.select("path", "batch") for p in parts))
        newest = at.groupBy("path").agg(F.max("batch").alias("newest"), F.count("*").alias("n")).where("n > 1").select("path", "newest")
        older = at.join(newest, "path").where("batch < newest").select("path", "batch")
        return out.join(older, ["path", "batch"], "left_anti")

    def rows(self, needed: Iterable[str]) -> DataFrame:
        """Identity columns and the needed summaries of all committed batches; of an object indexed twice the newest row."""
        manifest, readable = self.manifest(), self.indexes()
        needed = sorted(set(needed) & set(readable))
        types = {i: T._parse_datatype_json_string(readable[i]["type"]) for i in needed}
        sealed = {i: readable[i]["key_id"] for i in needed if readable[i]["key_id"]}
        raw = {i: T.StringType() if i in sealed else t for i, t in types.items()}
        if not manifest["batches"]:
            return self.spark.createDataFrame([], "path string, mtime long, size long, n_rows long")
        out = self._resolved([self._read(b, raw, n) for n, b in enumerate(manifest["batches"])])
        for i, key in sealed.items():
            opened = F.try_aes_decrypt(F.unbase64(i), F.lit(bytearray(self.keys[key])), F.lit("GCM")).cast("string")
            out = out.withColumn(i, F.from_json(opened, types[i]))
        return out.select(*IDENTITY, *needed)

    def cached(self, needed: Iterable[str]) -> DataFrame:
        """The same, kept in memory or on local disk."""
        k = frozenset(needed)
        if k not in self._cached:
            self._cached[k] = self.rows(k).persist(StorageLevel.MEMORY_AND_DISK)
        return self._cached[k]

    def translate(self, test: KeepTest) -> Column:
        """The test as a condition on this store's rows."""
        return test.column()

    def denied(self, test: KeepTest, cached: bool = False) -> DataFrame:
        """(path, mtime, size) of the objects, as they were when summarised, that cannot satisfy the test."""
        known = self.cached(test.needs()) if cached else self.rows(test.needs())
        holds = F.col("n_rows").isNull() | (F.col("n_rows") > 0) & self.translate(test)
        return known.where(~F.coalesce(holds, F.lit(True))).select("path", "mtime", "size")

    def evaluate(self, test: KeepTest, listing: DataFrame, cached: bool = False) -> DataFrame:
        """(path, mtime, size, keep) of every object listed now; what is unknown or has changed since is kept."""
        known = self.cached(test.needs()) if cached else self.rows(test.needs())
        told = known.select("path", "mtime", "size", (F.col("n_rows").isNull() | (F.col("n_rows") > 0) & self.translate(test)).alias("holds"))
        return listing.join(told, ["path", "mtime", "size"], "left").select("path", "mtime", "size", F.coalesce("holds", F.lit(True)).alias("keep"))

    def drop_objects(self, gone: DataFrame, kinds: list) -> None:
        """Rewrite the store without the objects of ``gone`` (path), as one batch."""
        rows = self.rows([k.index for k in kinds]).join(gone, "path", "left_anti")
        self.write(rows, kinds, mode="replace")

    def bytes(self) -> int:
        """Bytes of the committed batches."""
        _, _, fs = self._fs()
        return sum(fs.getContentSummary(self._fs(b["name"])[1]).getLength() for b in self.manifest()["batches"])

    def read_bytes(self, needed: Iterable[str]) -> int:
        """Bytes that an evaluation reads which needs these summaries: here all of them."""
        return self.bytes()


class ParquetSummaryStore(SummaryStore):
    """Columnar files: a query reads only the summaries that its test needs."""

    def _append(self, rows, batch):
        rows.write.parquet(f"{self.path}/{batch}")

    def _load(self, batch, schema, needed):
        return self.spark.read.schema(schema).parquet(f"{self.path}/{batch}")

    def column_bytes(self) -> dict[str, int]:
        """Compressed bytes of each column of the committed batches, by the footers."""
        held = [b["name"] for b in self.manifest()["batches"]]
        if not held:
            return {}
        ship_package(self.spark)
        files = self.spark.read.format("binaryFile").option("pathGlobFilter", "*.parquet").load([f"{self.path}/{b}" for b in held])
        sizes = files.select(F.col("_metadata.file_path").alias("path")).mapInArrow(_column_bytes, "name string, bytes long")
        return {r.name: r.n for r in sizes.groupBy("name").agg(F.sum("bytes").alias("n")).collect()}

    def read_bytes(self, needed):
        """The identity columns and the needed ones only."""
        sizes = self.column_bytes()
        return sum(sizes.get(c, 0) for c in {*needed, *IDENTITY})


def _column_bytes(batches):
    """Compressed bytes of each top-level column of Parquet files."""
    from urllib.parse import unquote

    import pyarrow.parquet as pq
    from pyarrow import fs

    for batch in batches:
        for path in batch.column("path").to_pylist():
            where = unquote(path)
            system, inner = (fs.LocalFileSystem(), where.removeprefix("file://").removeprefix("file:")) if where.startswith("file:") else fs.FileSystem.from_uri(where)
            found: dict[str, int] = {}
            with system.open_input_file(inner) as f:
                meta = pq.ParquetFile(f).metadata
            for g in range(meta.num_row_groups):
                for c in range(meta.num_columns):
                    column = meta.row_group(g).column(c)
                    name = column.path_in_schema.split(".")[0]
                    found[name] = found.get(name, 0) + column.total_compressed_size
            yield pa.RecordBatch.from_pydict({"name": pa.array(list(found), pa.string()), "bytes": pa.array(list(found.values()), pa.int64())})


class DocumentSummaryStore(SummaryStore):
    """A JSON document for each object, as a search engine or key-value store would hold it."""

    def _append(self, rows, batch):
        rows.write.json(f"{self.path}/{batch}", ignoreNullFields=False)

    def _load(self, batch, schema, needed):
        return self.spark.read.schema(schema).json(f"{self.path}/{batch}")


class CatalogTableStore(SummaryStore):
    """Tables of the session's catalog; the manifest stays under ``path``."""

    def _name(self, batch: str) -> str:
        return "sift_" + batch.replace("-", "_")

    def _append(self, rows, batch):
        rows.write.saveAsTable(self._name(batch), format="parquet")

    def _load(self, batch, schema, needed):
        return self.spark.table(self._name(batch)).select(*schema.fieldNames())

    def bytes(self):
        """Not known without asking the catalog's file system."""
        return -1
