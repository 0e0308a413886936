"""Data sets as objects (files), with the identity and freshness of each."""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Identity of an object's content, as one string of constant metadata columns; Spark prunes files on it when planning.
OBJECT_KEY = "concat_ws('@', _metadata.file_path, cast(unix_micros(_metadata.file_modification_time) as string), cast(_metadata.file_size as string))"


#: Up to so many keys go into an IN list; the digests of more are packed into one literal.
IN_LIST = 5_000


def digest(key: Column) -> Column:
    """128 bits of an object key, in hexadecimal."""
    return F.md5(key.cast("binary"))


def among(key: Column, held: Iterable[str], digests: bool = False) -> Column:
    """Whether ``key`` is one of those ``held``, given as keys or as their digests; each key is looked up in a small group."""
    held = list(held)
    if len(held) <= IN_LIST:
        return (digest(key) if digests else key).isin(held)
    held = held if digests else [hashlib.md5(k.encode()).hexdigest() for k in held]
    groups: list[list[str]] = [[] for _ in range(len(held) // 8 + 1)]
    for d in held:
        groups[int(d[:8], 16) % len(groups)].append(d)
    packed = F.split(F.lit("\n".join(" ".join(g) for g in groups)), "\n")
    this = digest(key)
    return F.contains(F.get(packed, F.pmod(F.conv(F.left(this, F.lit(8)), 16, 10).cast("long"), F.lit(len(groups))).cast("int")), this)


_schemas: dict["LakeSource", T.StructType] = {}


@dataclass(frozen=True)
class LakeSource:
    """A data set at ``path`` in any file format that Spark reads; ``derive`` adds columns to what is read."""

    path: str
    fmt: str = "parquet"
    options: tuple[tuple[str, str], ...] = ()
    schema: str | None = None
    derive: Callable[[DataFrame], DataFrame] | None = field(default=None, compare=False)

    def read(self, spark: SparkSession) -> DataFrame:
        """The data set as it is now. Its schema is inferred once; ``forget`` after columns were added."""
        reader = spark.read.format(self.fmt).options(**dict(self.options))
        known = self.schema or _schemas.get(self)
        if known:
            reader = reader.schema(known)
        df = reader.load(self.path)
        if not known:
            # Values in directory names are left to be inferred: new ones may need another type.
            named = set(df._jdf.queryExecution().analyzed().relation().partitionSchema().fieldNames())
            _schemas[self] = T.StructType([f for f in df.schema if f.name not in named])
        return self.derive(df) if self.derive else df

    def forget(self) -> None:
        """Infer the schema anew at the next read."""
        _schemas.pop(self, None)

    def stream(self, spark: SparkSession) -> DataFrame:
        schema = self.schema or spark.read.format(self.fmt).options(**dict(self.options)).load(self.path).schema
        df = spark.readStream.format(self.fmt).options(**dict(self.options)).schema(schema).load(self.path)
        return self.derive(df) if self.derive else df

    def tagged(self, df: DataFrame, *columns: Column) -> DataFrame:
        """``columns`` of ``df`` with the object each row comes from: path, mtime, size."""
        return df.select(F.col("_metadata.file_path").alias("path"), F.expr("unix_micros(_metadata.file_modification_time)").alias("mtime"), F.col("_metadata.file_size").alias("size"), *columns)

    def listing(self, spark: SparkSession) -> DataFrame:
        """(path, mtime, size) of the objects that are there now, empty ones too; no content is read."""
        files = spark.read.format("binaryFile").option("recursiveFileLookup", "false").load(self.path)
        return self.tagged(files)
