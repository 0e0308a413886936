"""SimHash near-duplicate detection through a segment-popcount embedding.

A 64-bit fingerprint is embedded as the bit counts of its 32 two-bit segments. The Manhattan distance of two
embeddings never exceeds the Hamming distance of the fingerprints, so fingerprints at 3 or fewer differing bits lie
within Manhattan radius 3. The grid: coordinates are split into six groups; within radius 3 at most three groups can
differ, hence two near points share the joint value of at least three groups. Each of the 20 triples of groups is a
grid, each joint value a cell. Points meet in cells, pairs beyond the radius by Manhattan distance are dropped, and the
rest are verified exactly on the fingerprints. A large cell is divided again by quarters of the coordinates, one of which
any two near points share. Only a spanning forest of the verified links leaves a cell, so a dense group of near copies
yields a row per member, not a row per pair.

A segment's count is written in unary (none, one, both bits set: 00, 01, 11); so the Manhattan distance of two embeddings
is the number of bits by which their words differ.

Copies meet in one fingerprint before any pairing. Components come from alternating star contractions on tables.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sift.llm.textbatch import slices
from sift.runtime import materialise, ship_package

SHINGLE_WORDS = 3
SEED = 42
RADIUS = 3
#: Group borders over the 64 bits, whole two-bit segments each.
GROUPS = ((0, 12), (12, 24), (24, 34), (34, 44), (44, 54), (54, 64))


def text_fingerprint(text: str | None, shingle: int = SHINGLE_WORDS, seed: int = SEED) -> int:
    """The fingerprint of one text, unsigned. No word (or null): zero."""
    import xxhash

    words = (text or "").encode().lower().split()
    if not words:
        return 0
    flat = b" ".join(words)
    if len(words) <= shingle:
        hashes = np.array([xxhash.xxh64_intdigest(flat, seed)], np.uint64)
    else:
        size = np.fromiter(map(len, words), np.int64, len(words))
        end = np.cumsum(size + 1) - 1
        start = (end - size)[: len(words) - shingle + 1].tolist()
        digest = xxhash.xxh64_intdigest
        hashes = np.array([digest(flat[a:b], seed) for a, b in zip(start, end[shingle - 1 :].tolist(), strict=True)], np.uint64)
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        ones += np.unpackbits(hashes[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes), bitorder="little").tobytes(), "little")


def _fingerprint_batches(shingle: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                found = np.array([text_fingerprint(t, shingle, seed) for t in part.column("text").to_pylist()], np.uint64)
                yield pa.RecordBatch.from_arrays([part.column("doc"), part.column("key"), pa.array(found.view(np.int64))], ["doc", "key", "fp"])

    return run


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE_WORDS, seed: int = SEED) -> DataFrame:
    """(doc, key, fp): one row per row of ``docs``; fp is the fingerprint as a signed 64-bit integer, key a hash of the text."""
    ship_package(docs.sparkSession)
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).cast("long").alias("doc"), text_key(text).alias("key"), text.alias("text")).mapInArrow(_fingerprint_batches(shingle, seed), "doc long, key long, fp long")


def text_key(text: Column) -> Column:
    """With the id, tells rows apart that repeat an id."""
    return F.xxhash64(text)


_LOW = 0x5555555555555555


def embedded(fp: np.ndarray) -> np.ndarray:
    """The counts of all two-bit segments, in unary."""
    low, high = fp & np.uint64(_LOW), (fp >> np.uint64(1)) & np.uint64(_LOW)
    return (low | high) | ((low & high) << np.uint64(1))


def _near(fp: np.ndarray, counts: np.ndarray, node: np.uint64, at: np.uint64, radius: int) -> np.ndarray:
    """Which points are at ``radius`` bits or fewer from ``node``: first by the Manhattan bound, then exactly."""
    near = np.bitwise_count(counts ^ at) <= radius
    near[near] = np.bitwise_count(fp[near] ^ node) <= radius
    return near


def _pair_links(fp: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the graph on one cell's distinct fingerprints: each node linked to the one that reached it."""
    child, parent = [], []
    rest, counts = fp.copy(), embedded(fp)
    while rest.size > 1:
        front, rest, counts = [(rest[0], counts[0])], rest[1:], counts[1:]
        while front and rest.size:
            node, at = front.pop()
            near = _near(rest, counts, node, at, radius)
            if near.any():
                got = rest[near]
                child.append(got)
                parent.append(np.full(got.size, node, np.uint64))
                front.extend(zip(got, counts[near], strict=True))
                rest, counts = rest[~near], counts[~near]
    if not child:
        none = np.zeros(0, np.uint64)
        return none, none
    return np.concatenate(child), np.concatenate(parent)


#: Cells of more points are divided.
LARGE_CELL = 2048


def _cell_links(fp: np.ndarray, radius: int, large: int = LARGE_CELL) -> tuple[np.ndarray, np.ndarray]:
    """Links that connect all near points of a cell. Within radius 3 three quarters of the coordinates can differ, not all."""
    if fp.size <= large:
        return _pair_links(fp, radius)
    a, b, counts = [], [], embedded(fp)
    for quarter in range(4):
        value = (counts >> np.uint64(16 * quarter)) & np.uint64(0xFFFF)
        order = np.argsort(value, kind="stable")
        first = np.flatnonzero(np.r_[True, np.diff(value[order]) != 0])
        for x, y in zip(first.tolist(), [*first[1:].tolist(), len(fp)], strict=True):
            if y - x > 1:
                c, d = _pair_links(fp[order[x:y]], radius)
                a.append(c)
                b.append(d)
    none = np.zeros(0, np.uint64)
    return np.concatenate([none, *a]), np.concatenate([none, *b])


def _link_cells(radius: int):
    """Rows sorted by cell come in; verified links go out. Small cells are compared by shifted vectors, larger ones one by one."""

    def linked(cell: np.ndarray, fp: np.ndarray) -> Iterator[pa.RecordBatch]:
        first = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]])
        size = np.diff(np.r_[first, cell.size])
        a, b = [], []
        small, counts = np.repeat(size <= 16, size), embedded(fp)
        for shift in range(1, int(min(16, size.max()))):
            hit = np.flatnonzero((cell[shift:] == cell[:-shift]) & small[shift:])
            hit = hit[np.bitwise_count(counts[hit] ^ counts[hit + shift]) <= radius]
            hit = hit[np.bitwise_count(fp[hit] ^ fp[hit + shift]) <= radius]
            a.append(fp[hit + shift])
            b.append(fp[hit])
        for s, n in zip(first[size > 16].tolist(), size[size > 16].tolist(), strict=True):
            x, y = _cell_links(np.unique(fp[s : s + n]), radius)
            a.append(x)
            b.append(y)
        if a:
            x, y = np.concatenate(a).view(np.int64), np.concatenate(b).view(np.int64)
            keep = x != y
            if keep.any():
                yield pa.RecordBatch.from_arrays([pa.array(x[keep]), pa.array(y[keep])], ["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tail: list[tuple[np.ndarray, np.ndarray]] = []  # of the cell that may go on in the next batch

        def flush() -> Iterator[pa.RecordBatch]:
            if tail:
                yield from linked(np.concatenate([x for x, _ in tail]), np.concatenate([x for _, x in tail]))
                tail.clear()

        for batch in batches:
            if not batch.num_rows:
                continue
            cell, fp = batch.column(0).to_numpy(), batch.column(1).to_numpy().view(np.uint64)
            if tail and tail[0][0][0] != cell[0]:
                yield from flush()
            cut = int(np.searchsorted(cell, cell[-1]))
            if cut:
                tail.append((cell[:cut], fp[:cut]))
                yield from flush()
            tail.append((cell[cut:], fp[cut:]))
        yield from flush()

    return run


def pair_counts(fp: np.ndarray, radius: int = RADIUS) -> tuple[int, int, int]:
    """Of a sample of distinct fingerprints: all pairs, those within the Manhattan bound, and those that link."""
    counts = embedded(fp)
    by_bound = by_bits = 0
    for k in range(len(fp) - 1):
        near = np.bitwise_count(counts[k + 1 :] ^ counts[k]) <= radius
        by_bound += int(near.sum())
        by_bits += int((np.bitwise_count(fp[k + 1 :][near] ^ fp[k]) <= radius).sum())
    return len(fp) * (len(fp) - 1) // 2, by_bound, by_bits


def near_links(points: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Links (a, b) among the distinct fingerprints of ``points.fp``: a spanning forest of each cell's exact links.

    Any two fingerprints at ``radius`` (up to 3) or fewer differing bits are connected through the links. A cell's task
    holds eight bytes for each distinct fingerprint in the cell.
    """
    if radius > RADIUS:
        raise ValueError("the grid is laid out for a radius of 3 or less")
    ship_package(points.sparkSession)
    low, high = F.col("fp").bitwiseAND(_LOW), F.shiftrightunsigned("fp", 1).bitwiseAND(_LOW)
    unary = low.bitwiseOR(high).bitwiseOR(F.shiftleft(low.bitwiseAND(high), 1))
    point = points.select("fp").distinct().withColumn("embedded", unary)
    cells = []
    for k, three in enumerate(combinations(GROUPS, 3)):
        mask = sum((1 << b) - (1 << a) for a, b in three)
        cells.append(F.xxhash64(F.lit(k), F.col("embedded").bitwiseAND(F.lit(mask - (1 << 64) if mask >> 63 else mask))))
    dealt = point.select(F.explode(F.array(*cells)).alias("cell"), "fp").repartition("cell").sortWithinPartitions("cell", "fp")
    return dealt.mapInArrow(_link_cells(radius), "a long, b long").distinct()


#: Rounds of star contraction at most; a path of n nodes needs about log2(n) of them.
ROUNDS = 200


def components(links: DataFrame, label: str = "cc") -> DataFrame:
    """(node, root): each linked node with the smallest node reachable; by alternating large- and small-star steps."""
    both = F.array(F.struct(F.col("a").alias("u"), F.col("b").alias("v")), F.struct(F.col("b").alias("u"), F.col("a").alias("v")))
    edges = materialise(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), f"{label}-0")
    seen = None
    for k in range(1, ROUNDS + 1):
        state = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == seen or not state[0]:
            break
        seen = state
        pair = edges.select(F.explode(both).alias("e")).select("e.u", "e.v")
        least = pair.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        edges = pair.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        down = edges.groupBy("a").agg(F.min("b").alias("m"))
        small = edges.join(down, "a")
        edges = small.select(F.col("b").alias("a"), F.col("m").alias("b")).union(small.select("a", F.col("m").alias("b"))).where("a <> b").distinct()
        edges = materialise(edges, f"{label}-{k}")
    else:
        raise RuntimeError(f"components are not stable after {ROUNDS} rounds")
    return edges.select(F.col("a").alias("node"), F.col("b").alias("root")).union(edges.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """(doc, key, fp, root, component): every row of ``docs`` with its fingerprint, its component and the smallest id there.

    root names the component by one of its fingerprints. Null or wordless texts have fingerprint zero and are linked
    like any other. Repeated rows share their component; a null id takes no part in the minimum (a component of null ids
    only has a null component). An empty table gives an empty result. Other columns of ``docs`` are not looked at.
    """
    marked = materialise(fingerprints(docs, id_col, text_col), "simhash")
    least = marked.groupBy("fp").agg(F.min("doc").alias("least"))
    roots = components(near_links(marked, radius))
    placed = least.join(roots, least.fp == roots.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    named = placed.groupBy("root").agg(F.min("least").alias("component"))
    of = materialise(placed.join(named, "root").select("fp", "root", "component"), "simhash-of")
    return marked.join(of, "fp").select("doc", "key", "fp", "root", "component")


def without_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """``docs`` with one row of each component: that of the smallest id (rows without an id come last, then by text)."""
    found = near_duplicates(docs, id_col, text_col, radius)
    keep = found.groupBy("root").agg(F.min(F.struct(F.col("doc").isNull().alias("late"), "doc", "key")).alias("_k")).select(F.col("_k.doc").alias("_keep_doc"), F.col("_k.key").alias("_keep_key"))
    keep = materialise(keep, "simhash-keep")
    rows = docs.join(keep, docs[id_col].cast("long").eqNullSafe(keep["_keep_doc"]) & (text_key(docs[text_col].cast("string")) == keep["_keep_key"]), "left_semi")
    # Only where the kept rows themselves are repeated has anything to be compared.
    repeated = found.groupBy("doc", "key").agg(F.count("*").alias("n")).where("n > 1").join(keep, F.col("doc").eqNullSafe(F.col("_keep_doc")) & (F.col("key") == F.col("_keep_key")), "left_semi")
    return rows.dropDuplicates([id_col, text_col]) if repeated.take(1) else rows


def op10_simhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    """Fingerprint and component of every document, under the contract's shingles and radius."""
    found = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select(F.col("doc").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))
