"""Substring dedup by content-defined chunking with a gear rolling hash.

A chunk ends where the gear hash of the last 16 bytes has its top bits zero, wherever in a text those bytes stand, once
the chunk is long enough, and never inside a character: an insertion moves the chunks after it but does not change them. Chunks are
counted by a 64-bit digest. A long enough row of adjacent chunks that other texts hold too is a repeated passage; as it
takes several chunks, one chance collision of digests makes none. The first occurrence of a digest, in the text of the
smallest id, is its owner; all others may be cut, and each chunk survives once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sift.llm.expr import fresh
from sift.llm.textbatch import flat, slices
from sift.runtime import materialise, ship_package

#: A border is at one of 2**BITS places on average.
BITS = 4
#: Bytes of the shortest chunk, and of the shortest repeated stretch that is reported.
MIN_CHUNK = 12
MIN_REPEAT = 72


def gear_table() -> np.ndarray:
    """256 random 16-bit values, from a fixed seed."""
    return np.random.default_rng(20_011).integers(0, 1 << 16, 256, dtype=np.uint16)


_GEAR = gear_table()


def gear_hash(buf: np.ndarray) -> np.ndarray:
    """The rolling hash h -> 2h + gear[byte] (16 bits) at every byte: by doubling, the sum over the last 1, 2, 4, 8, 16 bytes."""
    h = _GEAR[buf]
    for width in (1, 2, 4, 8):
        moved = np.zeros_like(h)
        moved[width:] = h[:-width] << np.uint16(width)
        h = h + moved
    return h


def cuts(buf: np.ndarray, offsets: np.ndarray, bits: int = BITS, min_chunk: int = MIN_CHUNK) -> list[int]:
    """Chunk borders in a buffer of texts, those of the texts included; no text's borders depend on another."""
    h = gear_hash(buf)
    size = np.diff(offsets)
    head = np.minimum(size, 15)  # bytes whose hash still looks back into the text before
    at = np.repeat(offsets[:-1], head) + np.arange(head.sum()) - np.repeat(np.cumsum(head) - head, head)
    low = np.uint16(16 - bits)
    border = h >> low == 0
    border[at] = False
    border[:-1] &= (buf[1:] & 0xC0) != 0x80
    out, last = [0], 0
    ends = set(offsets.tolist())
    for e in np.union1d(np.flatnonzero(border) + 1, offsets).tolist():
        if e - last >= min_chunk or e in ends:
            if e > last:
                out.append(e)
                last = e
    return out


def _chunk_batches(bits: int, min_chunk: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        digest = xxhash.xxh3_64_intdigest
        for batch in batches:
            for part in slices(batch, "text"):
                buf, offsets = flat(part.column("text"))
                raw = buf.tobytes()
                edge = cuts(buf, offsets, bits, min_chunk)
                sums = np.array([digest(raw[a:b]) for a, b in zip(edge, edge[1:], strict=False)], np.uint64).view(np.int64)
                start, end = np.array(edge[:-1], np.int64), np.array(edge[1:], np.int64)
                row = np.searchsorted(offsets, start, side="right") - 1
                yield pa.RecordBatch.from_arrays([part.column("doc").take(pa.array(row)), pa.array((start - offsets[row]).astype(np.int32)), pa.array((end - offsets[row]).astype(np.int32)), pa.array(sums)], ["doc", "a", "b", "digest"])

    return run


def chunks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bits: int = BITS, min_chunk: int = MIN_CHUNK) -> DataFrame:
    """(doc, a, b, digest): the chunks of every text, as byte spans."""
    ship_package(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).cast("string").alias("text")).mapInArrow(_chunk_batches(bits, min_chunk), "doc long, a int, b int, digest long")


def repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bits: int = BITS, min_chunk: int = MIN_CHUNK, min_repeat: int = MIN_REPEAT, within: bool = False) -> DataFrame:
    """(doc, start, end, n_chunks, n_docs, other, first): stretches of chunks that other texts hold too, at least ``min_repeat`` bytes in a row.

    start and end are byte offsets; ``first`` tells whether the stretch owns its chunks, and so stays when the rest is
    cut; a row of repeated chunks is told in parts where that changes. ``n_docs`` is the largest number of occurrences
    among its chunks; ``other`` the smallest id that shares its first chunk (in the text that has the smallest itself,
    the largest). What is repeated inside one text only counts if ``within`` is set. Rows without an id are left out;
    rows that repeat an id are one document. Null and empty texts have no chunks; an empty table gives no rows.
    """
    found = materialise(chunks(docs.where(F.col(id_col).isNotNull()), id_col, text_col, bits, min_chunk), "chunks")
    # Stored, so that both sides of the join are plain exchanges, of which a frequent digest's can be split.
    shared = found.groupBy("digest").agg(F.min("doc").alias("lo"), F.max("doc").alias("hi"), F.count("*").alias("n"))
    shared = materialise(shared.where("n > 1" if within else "lo <> hi"), "chunks-shared")
    seen = found.join(shared, "digest")
    again = F.row_number().over(Window.partitionBy("doc", "digest").orderBy("a", "b"))
    seen = seen.select("doc", "a", "b", "n", F.when(F.col("doc") == F.col("lo"), F.col("hi")).otherwise(F.col("lo")).alias("other"), ((F.col("doc") == F.col("lo")) & (again == 1)).alias("first"))
    along = Window.partitionBy("doc").orderBy("a", "b")
    begins = F.coalesce(F.col("a") > F.lag("b").over(along), F.lit(True))
    turns = begins | (F.col("first") != F.lag("first").over(along))
    upto = along.rowsBetween(Window.unboundedPreceding, 0)
    rows = seen.select("*", begins.cast("int").alias("begins"), turns.cast("int").alias("turns")).select("*", F.sum("begins").over(upto).alias("row"), F.sum("turns").over(upto).alias("part"))
    parts = rows.groupBy("doc", "row", "part").agg(F.min("a").alias("start"), F.max("b").alias("end"), F.count("*").alias("n_chunks"), F.max("n").alias("n_docs"), F.min_by("other", "a").alias("other"), F.first("first").alias("first"))
    whole = Window.partitionBy("doc", "row")
    parts = parts.withColumn("long", F.max("end").over(whole) - F.min("start").over(whole))
    return parts.where(F.col("long") >= min_repeat).select("doc", "start", "end", "n_chunks", "n_docs", "other", "first")


def without_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bits: int = BITS, min_chunk: int = MIN_CHUNK, min_repeat: int = MIN_REPEAT, within: bool = False) -> DataFrame:
    """``docs`` with the repeated passages cut out of their texts, but for the one stretch that owns them.

    Every row stays, its text maybe empty. Rows without an id, and rows that share an id, are left as they are. Other
    columns are untouched.
    """
    mark = fresh(docs, "_cut")
    cut = repeated_passages(docs, id_col, text_col, bits, min_chunk, min_repeat, within).where("not first")
    alone = docs.groupBy(F.col(id_col).cast("long").alias("doc")).agg(F.count("*").alias("rows")).where("rows = 1").select("doc")
    spans = cut.join(alone, "doc", "left_semi").groupBy("doc").agg(F.array_sort(F.collect_list(F.struct("start", "end"))).alias(mark)).withColumnRenamed("doc", f"{mark}_of")
    raw = F.encode(F.col(f"`{text_col}`"), "UTF-8")
    begins, ends = F.concat(F.array(F.lit(0)), F.col(f"{mark}.end")), F.concat(F.col(f"{mark}.start"), F.array(F.octet_length(F.col(f"`{text_col}`"))))
    kept = F.transform(F.arrays_zip(begins.alias("a"), ends.alias("b")), lambda x: F.decode(F.substring(raw, x["a"] + 1, x["b"] - x["a"]), "UTF-8"))
    joined = docs.join(spans, docs[id_col].cast("long") == F.col(f"{mark}_of"), "left")
    text = F.when(F.col(mark).isNull(), F.col(f"`{text_col}`")).otherwise(F.array_join(kept, ""))
    return joined.select(*(text.alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns))


def op7_substring_dedup(spark, sf_dir: str) -> DataFrame:
    """Repeated passages of all documents."""
    return repeated_passages(spark.read.parquet(f"{sf_dir}/documents.parquet")).withColumnRenamed("doc", "doc_id").withColumnRenamed("other", "other_doc_id")
