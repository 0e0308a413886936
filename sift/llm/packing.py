"""Best-fit packing of tokenised documents into fixed-length sequences, by hierarchical residual packing.

A document is its token ids and an end id. Only documents longer than a sequence are cut, into full pieces and a rest.
Pieces are dealt to tasks; each task packs its own best-fit, longest first, and emits its bins. Two bins that are both
more than half full can never be merged, so what goes up the tree are the bins at most half full and, as hosts for
them, a few bins with the widest residuals; there they are items, packed best-fit again by the task of the next level,
until one task is left. Only lengths travel, never tokens.
"""

from __future__ import annotations

import json
import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sift.llm.textbatch import IS_SOLID, flat, slices, spread, word_bounds, word_digests
from sift.runtime import materialise, ship_package

CAPACITY = 2048
END_ID = 0
#: Pieces that one task packs, and tasks of one level that meet in one of the next.
TASK_PIECES = 20_000
FAN_IN = 8
#: Bins with the widest residuals that accompany each group's half-empty ones.
HOSTS = 16
#: Words whose ids a worker keeps: some 40 bytes each. Beyond, the half that wasn't met for longest goes.
CACHE_WORDS = 500_000
#: Bytes of text that are encoded at once.
ENCODE_BYTES = 4 << 20
#: Runs of more bytes are left to the tokenizer's own encoder.
RUN_BYTES = 32
#: Words that are merged side by side.
_MERGED = 100_000

# Classes of bytes: letters (ASCII, and two-byte Latin ones that composing leaves alone), digits, ASCII signs, others.
_LETTER, _DIGIT, _SIGN, _OTHER = range(4)
_CLASS = np.full(256, _OTHER, np.uint8)
_CLASS[33:127] = _SIGN
_CLASS[ord("'")] = _OTHER  # it may begin an ending of the pre-tokenizer's list
_CLASS[48:58] = _DIGIT
_CLASS[65:91] = _CLASS[97:123] = _LETTER
_LATIN, _TIMES, _DIVIDED = 0xC3, 0x97, 0xB7

_encoders: dict[str, "WordEncoder"] = {}


def _byte_characters() -> list[str]:
    """The characters by which byte-level tokenizers write bytes: printable ones as they are, others from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(others)) for b in range(256)]


class Merger:
    """Byte-pair merging of many runs side by side: in each step every run of a length merges its first pair of least rank."""

    def __init__(self, model: dict):
        vocab, end = model["vocab"], model["end_of_word_suffix"]
        self.middle, self.last = (np.array([vocab.get(c + e, -1) for c in _byte_characters()], np.int64) for e in ("", end))
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        self.size = 1 + max(vocab.values())
        code = np.array([vocab[a] * self.size + vocab[b] for a, b in pairs], np.int64)
        self.rank = np.argsort(code, kind="stable")
        self.code, self.none = code[self.rank], len(pairs)
        self.merged = np.array([vocab[a + b] for a, b in pairs], np.int64)

    def _ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        code = left * self.size + right
        at = np.minimum(np.searchsorted(self.code, code), len(self.code) - 1)
        return np.where(self.code[at] == code, self.rank[at], self.none)

    def ids(self, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All runs' ids in a row, and how many each has."""
        size, n, done = ends - starts, np.zeros(len(starts), np.int64), []
        for width in np.unique(size).tolist():
            of = np.flatnonzero(size == width)
            for k in range(0, len(of), _MERGED):
                done += self._merge(buf, starts, of[k : k + _MERGED], width)
        for of, symbols in done:
            n[of] = symbols.shape[1]
        at, out = np.cumsum(n) - n, np.zeros(n.sum(), "<u4")
        for of, symbols in done:
            out[at[of][:, None] + np.arange(symbols.shape[1])] = symbols
        return out, n

    def _merge(self, buf: np.ndarray, starts: np.ndarray, of: np.ndarray, width: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """(runs, their ids) by the number of ids; all runs of ``of`` have ``width`` bytes."""
        raw = buf[starts[of][:, None] + np.arange(width)]
        symbols = self.middle[raw]
        symbols[:, -1] = self.last[raw[:, -1]]
        if width == 1:
            return [(of, symbols)]
        ranks, done = self._ranks(symbols[:, :-1], symbols[:, 1:]), []
        while of.size:
            j = ranks.argmin(axis=1)
            least = ranks[np.arange(len(of)), j]
            open_ = least < self.none
            if not open_.all():
                done.append((of[~open_], symbols[~open_]))
                of, symbols, ranks, j, least = (x[open_] for x in (of, symbols, ranks, j, least))
                if not of.size:
                    break
            row, width = np.arange(len(of)), symbols.shape[1] - 1
            symbols[row, j] = self.merged[least]
            if width == 1:
                done.append((of, symbols[:, :1]))
                break
            keep = np.arange(width)
            symbols = np.take_along_axis(symbols, keep + (keep > j[:, None]), axis=1)
            keep = keep[:-1]
            ranks = np.take_along_axis(ranks, keep + (keep > j[:, None]), axis=1)
            for side, where in ((j - 1, j > 0), (j, j < width - 1)):
                r, c = row[where], side[where]
                ranks[r, c] = self._ranks(symbols[r, c], symbols[r, c + 1])
        return done


class WordEncoder:
    """Ids by a byte-level tokenizer that lower-cases and breaks at white space, letters, single digits and signs.

    Words are split at ASCII white space only, which that tokenizer drops; any other stays inside a word. Each distinct
    word of a slice of texts is looked up once, by a 128-bit digest. New words of plain letters, digits and signs are
    broken at the changes of class and merged side by side; any other is left to the tokenizer, so are long ones and
    those with both ``<`` and ``|``, which may spell a special token.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.merger = Merger(json.loads(self.tokenizer.to_str())["model"])
        # Known words, by digest: second digest, place and number of their ids in the pool, slice that met them last.
        self.key, self.proof = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
        self.at, self.n, self.met = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.pool, self.slice = np.zeros(0, "<u4"), 0

    def _learn(self, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All words' ids in a row, and how many each has."""
        size = ends - starts
        first = np.cumsum(size) - size
        raw = buf[spread(starts, size)]  # the words without gaps
        kind = _CLASS[raw]
        latin = np.flatnonzero(raw[:-1] == _LATIN)
        latin = latin[~np.isin(raw[latin + 1], (_TIMES, _DIVIDED))]
        kind[latin] = kind[latin + 1] = _LETTER
        low = raw.copy()
        low[(raw >= 65) & (raw <= 90)] += 32
        capital = latin[raw[latin + 1] < 0x9F] + 1
        low[capital] += 32
        border = np.ones(len(raw), bool)
        border[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == _DIGIT)
        border[first] = True
        start = np.flatnonzero(border)
        end = np.r_[start[1:], len(raw)]
        word = np.searchsorted(first, start, side="right") - 1
        slow = np.zeros(len(size), bool)
        slow[word[(kind[start] == _OTHER) | (end - start > RUN_BYTES)]] = True
        marked = [np.add.reduceat(raw == ord(c), first) > 0 for c in "<|"]
        slow |= marked[0] & marked[1]
        quick = ~slow[word]
        ids, n_run = self.merger.ids(low, start[quick], end[quick])
        n = np.bincount(word[quick], n_run, len(size)).astype(np.int64)
        hard = np.flatnonzero(slow)
        if hard.size:
            texts = [raw[a:b].tobytes().decode() for a, b in zip(first[hard].tolist(), (first + size)[hard].tolist(), strict=True)]
            found = [np.array(e.ids, "<u4") for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
            before = np.cumsum(n) - n
            pool = np.concatenate([ids, *found])
            n[hard] = list(map(len, found))
            before[hard] = len(ids) + np.cumsum(n[hard]) - n[hard]
            ids = pool[spread(before, n)]
        return ids, n

    def _know(self, key: np.ndarray, proof: np.ndarray, ids: np.ndarray, n: np.ndarray) -> None:
        """Take up new words."""
        at = self.pool.size + np.cumsum(n) - n
        self.pool = np.concatenate([self.pool, ids])
        both = [np.concatenate(x) for x in ((self.key, key), (self.proof, proof), (self.at, at), (self.n, n), (self.met, np.full(len(n), self.slice)))]
        order = np.argsort(both[0], kind="stable")
        self.key, self.proof, self.at, self.n, self.met = (x[order] for x in both)

    def _forget(self) -> None:
        """Keep what was met last, and its ids only."""
        keep = np.flatnonzero(self.met >= max(np.partition(self.met, -(CACHE_WORDS // 2))[-(CACHE_WORDS // 2)], self.met.min() + 1))
        self.key, self.proof, self.n, self.met = (x[keep] for x in (self.key, self.proof, self.n, self.met))
        self.pool = self.pool[spread(self.at[keep], self.n)]
        self.at = np.cumsum(self.n) - self.n

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """All texts' ids in a row as unsigned 32-bit integers, and the len+1 offsets into them; a null counts as empty."""
        buf, offsets = flat(texts)
        starts, ends, first = word_bounds(buf, offsets, IS_SOLID)
        digest = word_digests(buf, starts, ends)
        order = np.argsort(digest)
        ranked = digest[order]
        new = np.ones(len(ranked), bool)
        new[1:] = ranked[1:] != ranked[:-1]
        which = np.empty(len(ranked), np.int64)
        which[order] = np.cumsum(new) - 1
        key, one = ranked[new], order[new]
        proofs = word_digests(buf, starts, ends, 1)
        proof = proofs[one]
        self.slice += 1
        place = np.minimum(np.searchsorted(self.key, key), max(0, len(self.key) - 1))
        known = self.key[place] == key if len(self.key) else np.zeros(len(key), bool)
        if not (proofs == proof[which]).all() or not (self.proof[place[known]] == proof[known]).all():
            return self._plain(texts)  # two words of one digest
        self.met[place[known]] = self.slice
        if not known.all():
            fresh = np.flatnonzero(~known)
            self._know(key[fresh], proof[fresh], *self._learn(buf, starts[one[fresh]], ends[one[fresh]]))
            place = np.searchsorted(self.key, key)
        n = self.n[place][which]
        ids = self.pool[spread(self.at[place][which], n)]
        if len(self.key) > CACHE_WORDS:
            self._forget()
        return ids, np.r_[0, np.cumsum(n)][first]

    def _plain(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        found = [np.array(self.tokenizer.encode(t or "", add_special_tokens=False).ids, "<u4") for t in texts.to_pylist()]
        return np.concatenate([np.zeros(0, "<u4"), *found]), np.r_[0, np.cumsum(list(map(len, found)), dtype=np.int64)]


def encoder(path: str) -> WordEncoder:
    """This worker's encoder for a tokenizer file."""
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def _cut(path: str, capacity: int, end_id: int, with_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        coder, at = encoder(path), TaskContext.get().partitionId() << 33
        for batch in batches:
            for part in slices(batch, "text", ENCODE_BYTES):
                ids, first = coder.encode(part.column("text"))
                size = np.diff(first) + 1  # the end id too
                ends = np.cumsum(size)
                whole = np.full(ends[-1], end_id, "<u4")
                whole[np.arange(len(ids)) + np.repeat(np.arange(len(size)), size - 1)] = ids
                count = -(-size // capacity)
                row = np.repeat(np.arange(len(size)), count)
                piece = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
                start = piece * capacity
                length = np.minimum(size[row] - start, capacity)
                begin = (ends - size)[row] + start
                raw = memoryview(whole).cast("B")
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(begin.tolist(), (begin + length).tolist(), strict=True)]
                cols = [part.column("doc").take(pa.array(row)), pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length), pa.array(crc, pa.int64()), pa.array(np.arange(at, at + len(row)))]
                if with_ids:  # the pieces lie one after another
                    cols.append(pa.ListArray.from_arrays(pa.array(np.r_[begin, len(whole)].astype(np.int32)), pa.array(whole.view(np.int32))))
                at += len(row)
                yield pa.RecordBatch.from_arrays(cols, ["doc", "piece", "start", "length", "crc", "bin", "ids"][: len(cols)])

    return run


def cut_pieces(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, end_id: int = END_ID, with_ids: bool = False) -> DataFrame:
    """(doc, piece, start, length, crc, bin[, ids]): the pieces of every document, and if asked for their ids as array<int>."""
    ship_package(docs.sparkSession)
    schema = "doc long, piece int, start long, length long, crc long, bin long" + ", ids array<int>" * with_ids
    return docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).cast("string").alias("text")).mapInArrow(_cut(tokenizer_path, capacity, end_id, with_ids), schema)


def best_fit(sizes: list[int], capacity: int) -> list[list[int]]:
    """Bins of item indices: items in the given order, each into the fullest bin that takes it. Constant time an item."""
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    rooms, bins = 0, []
    for i, size in enumerate(sizes):
        fits = rooms >> size
        if fits:
            room = size + (fits & -fits).bit_length() - 1
            b = by_room[room].pop()
            if not by_room[room]:
                rooms ^= 1 << room
            bins[b].append(i)
        else:
            room, b = capacity, len(bins)
            bins.append([i])
        if room > size:
            left = room - size
            by_room[left].append(b)
            rooms |= 1 << left
    return bins


PACKED = "doc long, piece int, start long, length long, crc long, bin long, place long, open boolean"


def _pack_level(capacity: int, last: bool, hosts: int):
    """Rows of the same bin are one item. Out: the rows with their new bin and place, and whether the bin goes up."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        read = [b for b in batches if b.num_rows]
        if not read:
            return
        t = pa.Table.from_batches(read)
        bins, place, length = (t.column(n).to_numpy() for n in ("bin", "place", "length"))
        order = np.lexsort((place, bins))
        bins, place, length = bins[order], place[order], length[order]
        first = np.flatnonzero(np.r_[True, bins[1:] != bins[:-1]])
        size = np.add.reduceat(length, first)
        count = np.diff(np.r_[first, bins.size])
        ranked = np.lexsort((bins[first], -size))
        packed = best_fit(size[ranked].tolist(), capacity)
        new_bin, shift = np.zeros(len(first), np.int64), np.zeros(len(first), np.int64)
        fill = np.zeros(len(packed), np.int64)
        for b, items in enumerate(packed):
            at = 0
            for i in items:
                j = ranked[i]
                new_bin[j], shift[j] = b, at
                at += int(size[j])
            fill[b] = at
        up = np.zeros(len(packed), bool)
        if not last:
            up[fill <= capacity // 2] = True
            up[np.argsort(fill, kind="stable")[: int(up.sum()) + hosts]] = True
            up[fill == capacity] = False
        name = np.array([bins[first[ranked[items[0]]]] for items in packed], np.int64)
        of = np.repeat(new_bin, count)
        t = t.take(pa.array(order))
        yield from pa.Table.from_arrays([*(t.column(n) for n in ("doc", "piece", "start", "length", "crc")), pa.array(name[of]), pa.array(place + np.repeat(shift, count)), pa.array(up[of])], ["doc", "piece", "start", "length", "crc", "bin", "place", "open"]).to_batches(max_chunksize=10_000)

    return run


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY, task_pieces: int = TASK_PIECES, fan_in: int = FAN_IN, hosts: int = HOSTS) -> DataFrame:
    """The pieces with their bin (sequence) and place in it, no bin over ``capacity``; ``pieces`` must be a stored table."""
    ship_package(pieces.sparkSession)
    tasks = max(1, -(-pieces.count() // task_pieces))
    rows, done = pieces.withColumn("place", F.lit(0).cast("long")), None
    level = 0
    while True:
        packed = rows.repartition(tasks, F.xxhash64("bin", F.lit(level))).select("doc", "piece", "start", "length", "crc", "bin", "place").mapInArrow(_pack_level(capacity, tasks == 1, hosts), PACKED)
        packed = materialise(packed, f"pack-{level}")
        shut = packed.where("not open").drop("open")
        done = shut if done is None else done.unionByName(shut)
        if tasks == 1:
            return done
        rows, tasks, level = packed.where("open").drop("open"), -(-tasks // fan_in), level + 1


def pack_documents(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """(doc, piece, start, length, crc, bin, place) for every document.

    A null or empty text is the end id alone. Repeated rows and ids are packed as so many documents; a null id stays
    null. An empty table gives no rows. Other columns are not looked at.
    """
    return pack_pieces(materialise(cut_pieces(docs, tokenizer_path, id_col, text_col, capacity, end_id), "pieces"), capacity)


def sequences(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """(sequence, ids, docs): the packed sequences themselves, ids as array<int>, each at most ``capacity`` long."""
    pieces = materialise(cut_pieces(docs, tokenizer_path, id_col, text_col, capacity, end_id, with_ids=True), "pieces-ids")
    packed = pack_pieces(pieces.drop("ids"), capacity)
    whole = packed.join(pieces.select(F.col("doc").alias("d"), F.col("piece").alias("p"), F.col("bin").alias("origin"), "ids", F.col("crc").alias("c")), F.col("doc").eqNullSafe(F.col("d")) & (F.col("piece") == F.col("p")) & (F.col("crc") == F.col("c")))
    whole = whole.dropDuplicates(["bin", "place"])
    held = whole.groupBy("bin").agg(F.array_sort(F.collect_list(F.struct("place", "doc", "piece", "length", "ids"))).alias("held"))
    return held.select(F.col("bin").alias("sequence"), F.expr("flatten(transform(held, x -> x.ids))").alias("ids"), F.expr("transform(held, x -> struct(x.doc, x.piece, x.place, x.length))").alias("docs"))


def op3_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    """Every document of the table packed into sequences of 2048 tokens."""
    import public_tokenizers

    return contract_rows(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("word_bpe_49k.json"))


def contract_rows(docs: DataFrame, tokenizer_path: str) -> DataFrame:
    """``pack_documents`` under the contract's column names."""
    packed = pack_documents(docs, tokenizer_path)
    return packed.select(F.col("doc").alias("doc_id"), "piece", "start", "length", F.col("crc").alias("ids_crc32"), F.col("bin").alias("sequence_id"), F.col("place").alias("offset"))
