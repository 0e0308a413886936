"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

The test strings are the 13-word windows of the benchmark items (an item of fewer words is one window). For each window
length there is a table of shifts indexed by hashed two-word blocks: standing on a possible last word of a window, the
block there tells how far the next possible end lies. Where the shift is zero the hash of the whole window selects a
bucket, and the words themselves are compared. The tables are arrays in files that the workers map. All texts of a slice are searched side by side, a lane for each stretch
of words, so that every step is one vector operation.
"""

from __future__ import annotations

import json
import os
import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sift.llm.textbatch import ASCII_LOWER, flat, slices, spread, word_bounds, word_digests, word_keys
from sift.runtime import ship_package

WINDOW = 13
#: Characters of benchmark text whose tables are built at once, in some ten times as many bytes.
BLOCK_BYTES = 16 << 20
LANE_WORDS = 256
#: Bytes of documents searched side by side.
SEARCH_BYTES = 2 << 20
_WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_IS_WORD = np.ones(256, bool)
for _a, _b in ((0x00, 0x2F), (0x3A, 0x60), (0x7B, 0x7F)):
    _IS_WORD[_a : _b + 1] = False
_MIX = np.uint64(0x9E3779B97F4A7C15)
_TABLE_BITS = 18


def words_of(text: str | None) -> list[bytes]:
    """The contract's words: A-Z lower-cased, runs of digits, letters and bytes beyond ASCII."""
    return _WORD.findall((text or "").encode().lower())


def _blocks(keys: np.ndarray, m: int) -> np.ndarray:
    """Table index of the block that ends at each word; of one word alone for windows of one word."""
    mixed = keys * _MIX
    if m > 1 and len(keys):
        mixed[1:] += keys[:-1] * np.uint64(0xD6E8FEB86659FD93)
    return ((mixed ^ (mixed >> np.uint64(31))) >> np.uint64(64 - _TABLE_BITS)).astype(np.int64) if len(keys) else np.zeros(0, np.int64)


def _window_hash(keys: np.ndarray, last: np.ndarray, m: int) -> np.ndarray:
    """Hash of the m words that end at each of ``last``."""
    h = np.zeros(len(last), np.uint64)
    for k in range(m):
        h = (h ^ keys[last - m + 1 + k]) * _MIX
        h ^= h >> np.uint64(32)
    return h


class Searcher:
    """The tables for windows of one length, as arrays.

    shift: by block. hashes: of the distinct windows, sorted; equal ones, if any, in a row. at: first word of each in the
    block's benchmark text. item_at, item: the items of each window, as indices.
    """

    FIELDS = ("shift", "hashes", "at", "item_at", "item")

    def __init__(self, m: int, shift: np.ndarray, hashes: np.ndarray, at: np.ndarray, item_at: np.ndarray, item: np.ndarray):
        self.m, self.shift, self.hashes, self.at, self.item_at, self.item = m, shift, hashes, at, item_at, item

    @classmethod
    def build(cls, m: int, keys: np.ndarray, digests: np.ndarray, at: np.ndarray, item: np.ndarray) -> Searcher:
        """From the words' keys and full digests, the first word of each window and its item; windows may be repeated."""
        block = min(2, m)
        blocks = _blocks(keys, m)
        shift = np.full(1 << _TABLE_BITS, m - block + 1, np.uint8)
        for j in range(block - 1, m):
            np.minimum.at(shift, blocks[at + j], m - 1 - j)
        search, proof = (_window_hash(x, at + m - 1, m) for x in (keys, digests))
        order = np.lexsort((item, proof, search))
        search, proof, at, item = search[order], proof[order], at[order], item[order]
        new = np.ones(len(at), bool)
        new[1:] = (search[1:] != search[:-1]) | (proof[1:] != proof[:-1])
        own = new.copy()
        own[1:] |= item[1:] != item[:-1]
        return cls(m, shift, search[new], at[new], np.r_[np.flatnonzero(new[own]), own.sum()], item[own].astype(np.int32))

    def search(self, keys: np.ndarray, first_word: np.ndarray) -> np.ndarray:
        """Last words of the windows that may be test strings: hash equal, words still to be compared."""
        m, blocks = self.m, _blocks(keys, self.m)
        begin, end = first_word[:-1], first_word[1:]
        lanes = np.maximum(0, -(-(end - begin - m + 1) // LANE_WORDS))
        text = np.repeat(np.arange(len(lanes)), lanes)
        nth = np.arange(len(text)) - np.repeat(np.cumsum(lanes) - lanes, lanes)
        at = begin[text] + m - 1 + nth * LANE_WORDS
        stop = np.minimum(at + LANE_WORDS, end[text])
        found = []
        while at.size:
            jump = self.shift[blocks[at]]
            zero = jump == 0
            if zero.any():
                found.append(at[zero])
            at = at + np.maximum(jump, 1)
            live = at < stop
            at, stop = at[live], stop[live]
        if not found:
            return np.zeros(0, np.int64)
        last = np.sort(np.concatenate(found))
        h = _window_hash(keys, last, m)
        where = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
        return last[self.hashes[where] == h]

    def candidates(self, keys: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(last word, window) of all windows in the bucket of each place."""
        h = _window_hash(keys, last, self.m)
        low, high = (np.searchsorted(self.hashes, h, side) for side in ("left", "right"))
        return np.repeat(last, high - low), spread(low, high - low)


#: Places compared word by word at once.
_COMPARED = 8192


class Block:
    """The benchmark text of one block, its words, and a searcher for each window length that occurs."""

    def __init__(self, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, items: list[str | None], searchers: list[Searcher]):
        self.buf, self.starts, self.ends, self.items, self.searchers = buf, starts, ends, items, searchers

    @classmethod
    def build(cls, benchmark: list[tuple[str | None, str]], window: int = WINDOW) -> Block:
        """Of (item, text); items without words have no windows."""
        buf, offsets = flat(pa.array([t for _, t in benchmark], pa.string()))
        buf = ASCII_LOWER[buf]
        starts, ends, first = word_bounds(buf, offsets, _IS_WORD)
        keys, digests = word_keys(buf, starts, ends), word_digests(buf, starts, ends)
        size = np.diff(first)
        length = np.minimum(size, window)
        searchers = []
        for m in np.unique(length[size > 0]).tolist():
            of = np.flatnonzero(length == m)
            n = size[of] - m + 1
            searchers.append(Searcher.build(m, keys, digests, spread(first[of], n), np.repeat(of, n)))
        return cls(buf, starts, ends, [i for i, _ in benchmark], searchers)

    def save(self, path: str) -> None:
        """One file: a line that tells names, types and lengths, then the arrays."""
        arrays = {"buf": self.buf, "starts": self.starts, "ends": self.ends}
        for s in self.searchers:
            arrays |= {f"{s.m}.{f}": getattr(s, f) for f in Searcher.FIELDS}
        held = [(n, x.dtype.str, len(x)) for n, x in arrays.items()]
        with open(path, "wb") as f:
            f.write(json.dumps({"arrays": held, "items": self.items}).encode() + b"\n")
            for x in arrays.values():
                f.write(bytes(-f.tell() % 8))
                f.write(np.ascontiguousarray(x).data)

    @classmethod
    def load(cls, path: str) -> Block:
        """The arrays stay in the file, mapped: they take up no worker's memory beyond what is being read."""
        with open(path, "rb") as f:
            head = json.loads(f.readline())
            at = f.tell()
        raw = np.memmap(path, np.uint8, "r")
        arrays = {}
        for name, kind, n in head["arrays"]:
            at += -at % 8
            size = n * np.dtype(kind).itemsize
            arrays[name] = raw[at : at + size].view(kind)
            at += size
        lengths = sorted({int(n.split(".")[0]) for n in arrays if "." in n})
        return cls(arrays["buf"], arrays["starts"], arrays["ends"], head["items"], [Searcher(m, *(arrays[f"{m}.{f}"] for f in Searcher.FIELDS)) for m in lengths])

    def _equal(self, m: int, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, first: np.ndarray, other: np.ndarray) -> np.ndarray:
        """Whether the m words from each of ``first`` are those of the benchmark from ``other``."""
        out = np.zeros(len(first), bool)
        for k in range(0, len(first), _COMPARED):
            words = first[k : k + _COMPARED, None] + np.arange(m), other[k : k + _COMPARED, None] + np.arange(m)
            size = ends[words[0]] - starts[words[0]]
            same = (size == self.ends[words[1]] - self.starts[words[1]]).all(axis=1)
            left, right = (x[w[same]].ravel() for x, w in ((starts, words[0]), (self.starts, words[1])))
            n = size[same].ravel()
            differs = buf[spread(left, n)] != self.buf[spread(right, n)]
            if n.size:
                bounds = (np.cumsum(n) - n)[::m]
                same[same] = np.add.reduceat(differs, bounds, dtype=np.int64) == 0
            out[k : k + _COMPARED] = same
        return out

    def occurrences(self, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, first: np.ndarray, keys: np.ndarray) -> Iterator[tuple[np.ndarray, int, np.ndarray, np.ndarray]]:
        """(first words, window length, windows' item bounds) of confirmed occurrences."""
        for s in self.searchers:
            last, window = s.candidates(keys, s.search(keys, first))
            sure = self._equal(s.m, buf, starts, ends, last - s.m + 1, s.at[window])
            begin, window = last[sure] - s.m + 1, window[sure]
            n = s.item_at[window + 1] - s.item_at[window]
            yield begin, s.m, np.repeat(begin, n), s.item[spread(s.item_at[window], n)]


def search_slice(text: pa.Array, blocks: list[Block]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[list[str]]]:
    """(span offsets by text, a, b, words by text, items by text): what occurrences cover, as word intervals [a, b) merged where they meet."""
    buf, offsets = flat(text)
    buf = ASCII_LOWER[buf]
    starts, ends, first = word_bounds(buf, offsets, _IS_WORD)
    keys = word_keys(buf, starts, ends)
    begins, stops = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    items: list[set | None] = [None] * len(text)
    for block in blocks:
        for begin, m, at, item in block.occurrences(buf, starts, ends, first, keys):
            begins.append(begin)
            stops.append(begin + m)
            text_of = np.searchsorted(first, at, side="right") - 1
            pairs = np.unique(text_of * np.int64(len(block.items)) + item)
            for p in pairs.tolist():
                d, i = divmod(p, len(block.items))
                if items[d] is None:
                    items[d] = set()
                items[d].add(block.items[i])
    a, b = np.concatenate(begins), np.concatenate(stops)
    order = np.argsort(a, kind="stable")
    a, b = a[order], np.maximum.accumulate(b[order]) if len(a) else b
    # No interval leaves its text; those that meet across a border of texts are of two texts.
    text_of = np.searchsorted(first, a, side="right") - 1
    new = np.ones(len(a), bool)
    new[1:] = (a[1:] > b[:-1]) | (text_of[1:] != text_of[:-1])
    at = np.flatnonzero(new)
    a, b, text_of = a[at], b[np.r_[at[1:], len(new)] - 1] if len(at) else b[:0], text_of[at]
    bounds = np.searchsorted(text_of, np.arange(len(text) + 1))
    return bounds, a - first[text_of], b - first[text_of], np.diff(first), [sorted(x for x in i or () if x is not None) for i in items]


_blocks_read: dict[str, Block] = {}


def _block(name: str) -> Block:
    """This worker's view of a shipped block."""
    from pyspark import SparkFiles

    if name not in _blocks_read:
        _blocks_read[name] = Block.load(SparkFiles.get(name))
    return _blocks_read[name]


FOUND = "_n long, _hit long, _items array<string>, _spans array<struct<a:int,b:int>>"


def _search(shipped: list[str], names: list[str], text_col: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for gone in set(_blocks_read) - set(shipped):
            del _blocks_read[gone]
        blocks = [_block(name) for name in shipped]
        for batch in batches:
            for part in slices(batch, text_col, SEARCH_BYTES):
                bounds, a, b, n, items = search_slice(part.column(text_col), blocks)
                hit = np.r_[0, np.cumsum(b - a)][bounds]
                spans = pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.StructArray.from_arrays([pa.array(x.astype(np.int32)) for x in (a, b)], ["a", "b"]))
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in names), pa.array(n, pa.int64()), pa.array(np.diff(hit), pa.int64()), pa.array(items, pa.list_(pa.string())), spans], [*names, "_n", "_hit", "_items", "_spans"])

    return run


def ship_blocks(benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> list[str]:
    """Build the tables of (i, t) block by block and hand each to the executors as a file; the files' names."""
    spark = benchmark.sparkSession
    folder, names = tempfile.mkdtemp(prefix="sift-benchmark-"), []

    def ship(rows: list[tuple[str | None, str]]) -> None:
        block = Block.build(rows, window)
        if block.searchers:
            names.append(f"sift-benchmark-{uuid.uuid4().hex}")
            block.save(os.path.join(folder, names[-1]))
            spark.sparkContext.addFile(os.path.join(folder, names[-1]))

    held, size = [], 0
    for r in benchmark.toLocalIterator():
        if held and size + len(r.t) > block_bytes:
            ship(held)
            held, size = [], 0
        held.append((r.i, r.t))
        size += len(r.t)
    if held:
        ship(held)
    return names


def contamination(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES, carry: list[str] | None = None, name: str = "contamination") -> DataFrame:
    """The ``carry`` columns of ``docs`` (default: all but the text), then a struct of n_words, n_hit, items (sorted), spans, contaminated.

    spans are the word intervals that occurrences cover, merged where they meet. A null text has no words; a null item
    id marks words as hit but is in no list of items; repeated items count once. The benchmark is the bounded side: its
    tables are built for ``block_bytes`` of text at a time, and workers map them from files, so that neither the driver
    nor a task holds more than one block and the documents are read once. An empty benchmark finds nothing.
    """
    ship_package(docs.sparkSession)
    carry = [c for c in docs.columns if c != text_col] if carry is None else carry
    shipped = ship_blocks(benchmark.select(F.col(item_col).cast("string").alias("i"), F.col(item_text_col).cast("string").alias("t")).where("t is not null"), window, block_bytes)
    # The text itself is sent once, also where it is carried.
    same = docs.schema[text_col].dataType == T.StringType()
    names = ["_text" if same and c == text_col else f"_c{i}" for i, c in enumerate(carry)]
    read = docs.select(F.col(text_col).cast("string").alias("_text"), *(F.col(f"`{c}`").alias(n) for n, c in zip(names, carry, strict=True) if n != "_text"))
    kept = list(dict.fromkeys(names))
    schema = ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in read.select(*kept).schema), FOUND])
    state = read.mapInArrow(_search(shipped, kept, "_text"), schema)
    hit = F.col("_hit")
    told = F.struct(F.col("_n").alias("n_words"), hit.alias("n_hit"), F.col("_items").alias("items"), F.col("_spans").alias("spans"), ((hit > 0) & (20 * hit >= F.col("_n"))).alias("contaminated"))
    return state.select(*(F.col(n).alias(c) for n, c in zip(names, carry, strict=True)), told.alias(name))


def op5_benchmark_decontamination(spark, sf_dir: str) -> DataFrame:
    """Contamination of every document by the whole benchmark."""
    docs, bench = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    found = contamination(docs, bench, carry=["doc_id"]).select("doc_id", "contamination.*")
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), "contaminated")


_SQL_WORDS = r"regexp_extract_all(regexp_replace(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+', ' ', 'g'), '[^ ]+')"

ORACLE = f"""
WITH item AS (SELECT CAST(item_id AS VARCHAR) AS item, {_SQL_WORDS} AS w FROM benchmark),
long_item AS (SELECT item, w, least(13, len(w)) AS m FROM item WHERE len(w) > 0),
win AS (SELECT DISTINCT item, m, array_to_string(w[i:i + m - 1], ' ') AS s
        FROM (SELECT item, w, m, unnest(range(1, len(w) - m + 2)) AS i FROM long_item)),
lens AS (SELECT DISTINCT m FROM win),
doc AS (SELECT row_number() OVER () AS rid, doc_id, {_SQL_WORDS} AS w FROM documents),
pos AS (SELECT rid, m, i, array_to_string(w[i:i + m - 1], ' ') AS s
        FROM (SELECT rid, w, m, unnest(range(1, len(w) - m + 2)) AS i FROM doc, lens)),
occ AS (SELECT p.rid, p.i, p.m, win.item FROM pos p JOIN win ON win.s = p.s AND win.m = p.m),
hit AS (SELECT rid, count(DISTINCT k) AS n_hit FROM (SELECT rid, unnest(range(i, i + m)) AS k FROM occ) GROUP BY rid),
its AS (SELECT rid, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids FROM (SELECT DISTINCT rid, item FROM occ WHERE item IS NOT NULL) GROUP BY rid)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(h.n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(t.n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(t.ids, '')) AS items_sha256, coalesce(h.n_hit, 0) > 0 AND 20 * coalesce(h.n_hit, 0) >= len(d.w) AS contaminated
FROM doc d LEFT JOIN hit h ON h.rid = d.rid LEFT JOIN its t ON t.rid = d.rid
"""
