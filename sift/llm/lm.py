"""Language-model scoring by a weighted backoff automaton over words.

The model is an n-gram model of three words with Dirichlet smoothing: the probability of a word after a context is
(c + strength * lower) / (n + strength), where c counts the n-gram, n the context, and lower is the probability after the
context without its first word; below stand add-one unigrams. As an automaton: states are the seen contexts, an arc for
each n-gram ever seen carries that probability, and a failure arc to the shorter context carries strength / (n + strength).
A traversal from left to right keeps the longest seen context as its state. As that state depends on the last words only,
the places of a block of texts are traversed side by side. Every n-gram is kept, however rare.

Nothing that grows with the corpus is broadcast or collected. Texts are packed into blocks. Each block asks for the counts
of its own distinct n-grams: sorted digests, as gaps of a few bytes, dealt by ranges of digests to tasks that add up the
blocks' counts and answer each block in the order of its question. A block is then scored with what it got back. N-grams
are told apart by digests of 58 bits.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sift.llm.textbatch import ASCII_LOWER, IS_SOLID, flat, slices, spread, word_bounds, word_digests
from sift.runtime import ship_package

ORDER = 3
#: Weight of the shorter context, in counts: after one word, after two and more.
STRENGTHS = (4000.0, 8.0)
#: Bytes of text in a block, and bytes of the corpus for each range of digests.
BLOCK_BYTES = 4 << 20
RANGE_BYTES = 6 << 20
DIGEST_BITS = 58
_SHIFT = np.uint64(64 - DIGEST_BITS)
#: Digest of the end, before it is cut to its bits; the mark before a text's first word is the same.
_END = np.uint64(0x5851F42D4C957F2D)
_P1, _P2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def tokens_of(text: str | None) -> list[bytes]:
    """The contract's tokens: words between ASCII white space, A-Z lower-cased, and one end."""
    return [*(text or "").encode().lower().split(), b""]


def place_digests(buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Digests of the tokens of all texts, a mark before each text's first, and each place's distance from its mark."""
    buf = ASCII_LOWER[buf]
    starts, ends, first = word_bounds(buf, offsets, IS_SOLID)
    words = np.diff(first)
    out = np.full(len(starts) + 2 * len(words), _END)
    out[np.arange(len(starts)) + np.repeat(2 * np.arange(len(words)) + 1, words)] = word_digests(buf, starts, ends)
    size = words + 2
    return out, np.arange(len(out)) - np.repeat(np.cumsum(size) - size, size)


def longer(keys: np.ndarray, words: np.ndarray) -> np.ndarray:
    """Digests of one word more: of the n-gram that ends at the place before and the word here (none at the first place)."""
    out = np.zeros_like(keys)
    h = (keys[:-1] ^ (keys[:-1] >> np.uint64(31))) * _P1
    h ^= words[1:] * _P2
    h ^= h >> np.uint64(29)
    h *= _P1
    out[1:] = h ^ (h >> np.uint64(32))
    return out


def ngram_keys(words: np.ndarray, order: int) -> list[np.ndarray]:
    """For m from 1 the keys of the m-grams that end at each place; of one text where its distance is m - 1 at least."""
    raw = [words]
    for _ in range(1, order):
        raw.append(longer(raw[-1], words))
    return [k >> _SHIFT for k in raw]


def as_question(keys: np.ndarray, counts: np.ndarray, ranges: int) -> tuple[np.ndarray, int, np.ndarray, np.ndarray, np.ndarray]:
    """(asked keys, bytes a gap, gaps, counts of one byte, the ranges+1 bounds) for sorted distinct keys with their counts.

    A count beyond 255 repeats its key; a gap too wide for the chosen bytes is bridged by keys that count nothing. Each
    range's first gap is from the range's own beginning.
    """
    width_of = (1 << DIGEST_BITS) // ranges + 1
    times = np.maximum(1, -(-counts // 255))
    if len(times) and times.max() > 1:
        each = np.repeat(keys, times)
        last = np.cumsum(times) - 1
        c = np.full(len(each), 255, np.int64)
        c[last] = counts - 255 * (times - 1)
        keys, counts = each, c
    of = (keys // np.uint64(width_of)).astype(np.int64)
    begin = (of * width_of).astype(np.uint64)
    gaps = keys - begin
    if len(keys) > 1:
        same = of[1:] == of[:-1]
        gaps[1:][same] = (keys[1:] - keys[:-1])[same]
    size = [w * (len(keys) + int((gaps >> np.uint64(8 * w)).sum())) for w in range(4, 8)] + [8 * len(keys)]
    w = 4 + int(np.argmin(size))
    if w < 8:
        over = (gaps >> np.uint64(8 * w)).astype(np.int64)  # so many bridges before the key, each of the widest gap
        if over.any():
            most = np.uint64((1 << (8 * w)) - 1)
            over = (gaps // most).astype(np.int64)
            n = over + 1
            last = np.cumsum(n) - 1
            wide = np.full(n.sum(), most)
            wide[last] = gaps - over.astype(np.uint64) * most
            base = np.repeat(keys - gaps, n)
            step = np.arange(len(wide)) - np.repeat(last - over, n) + 1
            whole = base + step.astype(np.uint64) * most
            whole[last] = keys
            c = np.zeros(len(wide), np.int64)
            c[last] = counts
            gaps, keys, counts, of = wide, whole, c, np.repeat(of, n)
    return keys, w, gaps.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :w].ravel(), counts.astype(np.uint8), np.searchsorted(of, np.arange(ranges + 1))


def asked_keys(begin: np.ndarray, gaps: np.ndarray, sizes: np.ndarray, width: int) -> np.ndarray:
    """The keys of several questions in a row; ``begin`` is where the range of each begins, ``sizes`` their numbers of keys."""
    wide = np.zeros((len(gaps) // width, 8), np.uint8)
    wide[:, :width] = gaps.reshape(-1, width)
    step = wide.ravel().view("<u8").astype(np.uint64)
    at = np.cumsum(sizes) - sizes
    run = np.cumsum(step)  # modulo 2 ** 64, which the differences below don't mind
    return run + np.repeat(begin - (run[at] - step[at]), sizes)


def _binary(data: np.ndarray, bounds: np.ndarray) -> pa.Array:
    """Stretches of a byte buffer."""
    return pa.Array.from_buffers(pa.binary(), len(bounds) - 1, [None, pa.py_buffer(np.ascontiguousarray(bounds, np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def _bytes_of(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """All values of a binary column without gaps, and their sizes."""
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(0, np.int64)
    parts = [flat(c.cast(pa.binary())) for c in column.chunks if len(c)]
    return np.concatenate([x for x, _ in parts]), np.concatenate([np.diff(o) for _, o in parts])


#: Stretches of so many bytes are compressed.
_ZIPPED = 512


def _zip(data: np.ndarray, bounds: np.ndarray) -> pa.Array:
    """Stretches of a byte buffer, compressed where that makes long ones shorter."""
    if len(bounds) < 2 or np.diff(bounds).max() < _ZIPPED:
        return _binary(data, bounds)
    raw = [data[a:b].tobytes() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
    return pa.array([min(x, pa.compress(x, codec="zstd", asbytes=True), key=len) if len(x) >= _ZIPPED else x for x in raw], pa.binary())


def _unzip(column: pa.ChunkedArray, sizes: np.ndarray) -> np.ndarray:
    """The bytes of all stretches in a row; ``sizes`` are what they were before."""
    data, held = _bytes_of(column)
    if (held == sizes).all():
        return data
    ends = np.cumsum(held)
    parts = (data[e - h : e] if h == n else np.frombuffer(pa.decompress(data[e - h : e].tobytes(), n, codec="zstd", asbytes=True), np.uint8) for e, h, n in zip(ends.tolist(), held.tolist(), sizes.tolist(), strict=True))
    return np.concatenate(list(parts))


# -- words of the training texts


def _distinct(ranked: np.ndarray, flag: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of a sorted array, and how many flags each has."""
    if not len(ranked):
        return ranked, np.zeros(0, np.int64)
    first = np.flatnonzero(np.r_[True, ranked[1:] != ranked[:-1]])
    return ranked[first], np.add.reduceat(flag, first, dtype=np.int64)


def _question_rows(question, block: int) -> Iterator[pa.RecordBatch]:
    _, width, gaps, counts, bounds = question
    asked = np.flatnonzero(np.diff(bounds))
    for a in range(0, len(asked), 10_000):
        some = asked[a : a + 10_000]
        lo, hi = bounds[some[0]], bounds[some[-1] + 1]
        edge = np.r_[bounds[some], hi] - lo
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(np.full(len(some), block)), pa.array(np.full(len(some), width, np.int8)), _binary(gaps[lo * width : hi * width], edge * width), _zip(counts[lo:hi], edge)], ["range", "block", "width", "gaps", "counts"])


ASKED = "range long, block long, width byte, gaps binary, counts binary"


def _asked(table: pa.Table, ranges: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(keys, counts, number of keys by question, the questions' rows in ``table``) of one range."""
    width_of = (1 << DIGEST_BITS) // ranges + 1
    width = table.column("width").to_numpy()
    parts = []
    for w in np.unique(width).tolist():
        of = np.flatnonzero(width == w)
        t = table.take(pa.array(of))
        gaps, size = _bytes_of(t.column("gaps"))
        begin = t.column("range").to_numpy().astype(np.uint64) * np.uint64(width_of)
        parts.append((asked_keys(begin, gaps, size // w, w), _unzip(t.column("counts"), size // w), size // w, of))
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _count_words(ranges: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                words, depth = place_digests(*flat(part.column("text")))
                keys = np.sort((words >> _SHIFT)[depth > 0])
                yield from _question_rows(as_question(*_distinct(keys, np.ones(len(keys), bool)), ranges), 0)

    return run


def _add_up(ranges: int):
    def run(asked: pa.Table) -> pa.Table:
        keys, counts, _, _ = _asked(asked, ranges)
        held = np.sort(keys[counts > 0])
        return pa.table({"total": [int(counts.sum(dtype=np.int64))], "distinct": [len(_distinct(held, held)[0])]})

    return run


def vocabulary(texts: DataFrame, ranges: int) -> tuple[int, int]:
    """Tokens of all texts, and distinct ones."""
    ship_package(texts.sparkSession)
    asked = texts.mapInArrow(_count_words(ranges), ASKED)
    parts = max(ranges, int(texts.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    found = asked.repartition(parts, "range").groupBy("range").applyInArrow(_add_up(ranges), "total long, distinct long")
    return tuple(found.agg(*(F.coalesce(F.sum(c), F.lit(0).cast("long")) for c in ("total", "distinct"))).first())


# -- blocks


BLOCKS = "block long, docs array<long>, held array<boolean>, sizes array<int>, texts binary"


def _pack(block_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        at, held, size = TaskContext.get().partitionId() << 33, [], 0
        for batch in batches:
            for part in slices(batch, "text", block_bytes):
                nbytes = int(flat(part.column("text"))[1][-1])
                if held and size + nbytes > block_bytes:
                    yield packed(at, held)
                    at, held, size = at + 1, [], 0
                held.append(part)
                size += nbytes
        if held:
            yield packed(at, held)

    def packed(at: int, held: list[pa.RecordBatch]) -> pa.RecordBatch:
        t = pa.Table.from_batches(held).combine_chunks()
        buf, offsets = flat(t.column("text").chunk(0))
        whole = [t.column("doc").chunk(0), t.column("held_out").chunk(0), pa.array(np.diff(offsets).astype(np.int32))]
        zipped = pa.Codec("zstd", compression_level=3).compress(pa.py_buffer(np.ascontiguousarray(buf)), asbytes=True) if buf.size else b""
        return pa.RecordBatch.from_arrays([pa.array([at], pa.int64()), *(pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x) for x in whole), pa.array([zipped], pa.binary())], ["block", "docs", "held", "sizes", "texts"])

    return run


def _texts(sizes: np.ndarray, packed: bytes) -> tuple[np.ndarray, np.ndarray]:
    """The texts of a block as one buffer with offsets."""
    offsets = np.r_[0, np.cumsum(sizes, dtype=np.int64)]
    raw = pa.decompress(packed, int(offsets[-1]), codec="zstd", asbytes=True) if packed else b""
    return np.frombuffer(raw, np.uint8), offsets


def _places(sizes: np.ndarray, packed: bytes, order: int) -> tuple[np.ndarray, list[np.ndarray], list[np.ndarray]]:
    """Of a block: each place's distance from its text's mark, the keys by length, and at which places they are asked for."""
    words, depth = place_digests(*_texts(sizes, packed))
    # The mark before a text counts as no token.
    return depth, ngram_keys(words, order), [np.flatnonzero(depth >= max(1, m)) for m in range(order)]


def _fields(block: pa.RecordBatch, row: int) -> tuple:
    number, docs, held, sizes, packed = (block.column(n)[row] for n in ("block", "docs", "held", "sizes", "texts"))
    return number.as_py(), docs.values, held.values.to_numpy(zero_copy_only=False).astype(bool), sizes.values.to_numpy(), packed.as_py()


def _ask(order: int, ranges: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                number, _, held, sizes, packed = _fields(batch, row)
                depth, keys, of = _places(sizes, packed, order)
                taught = (~held).astype(np.uint64)[np.cumsum(depth == 0) - 1]
                both = np.concatenate([k[x] << np.uint64(1) | taught[x] for k, x in zip(keys, of, strict=True)])
                del keys, of, depth, taught
                both.sort()
                yield from _question_rows(as_question(*_distinct(both >> np.uint64(1), (both & np.uint64(1)).astype(bool)), ranges), number)

    return run


ANSWERS = "block long, range long, n int, low binary, at array<int>, high array<long>"


def _answer(ranges: int):
    """Counts of two bytes in the order asked, first all low bytes, then all high ones; and where and how many it is from 65,535 on."""

    def run(asked: pa.Table) -> pa.Table:
        keys, counts, size, rows = _asked(asked, ranges)
        order = np.argsort(keys)
        ranked = keys[order]
        new = np.r_[True, ranked[1:] != ranked[:-1]]
        total = np.add.reduceat(counts[order].astype(np.int64), np.flatnonzero(new))
        got = np.empty(len(keys), np.int64)
        got[order] = total[np.cumsum(new) - 1]
        bounds = np.r_[0, np.cumsum(size)]
        many = np.flatnonzero(got >= 65_535)
        edge = np.searchsorted(many, bounds)
        at = many - np.repeat(bounds[:-1], np.diff(edge))
        low = np.minimum(got, 65_535).astype("<u2").view(np.uint8).reshape(-1, 2)
        planes = np.empty(2 * len(got), np.uint8)
        each = np.repeat(bounds[:-1], size) + np.arange(len(got))
        planes[each], planes[each + np.repeat(size, size)] = low[:, 0], low[:, 1]
        low = _zip(planes, 2 * bounds)
        t = asked.select(["block", "range"]).take(pa.array(rows))
        edge = pa.array(edge.astype(np.int32))
        return pa.Table.from_arrays([*t.columns, pa.array(size.astype(np.int32)), low, pa.ListArray.from_arrays(edge, pa.array(at.astype(np.int32))), pa.ListArray.from_arrays(edge, pa.array(got[many]))], ["block", "range", "n", "low", "at", "high"])

    return run


SCORES = "doc long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
_SCORE_NAMES = ("doc", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score")


def traverse(depth: np.ndarray, counts: list[np.ndarray], contexts: list[np.ndarray], size: float, strengths: tuple[float, ...]) -> tuple[np.ndarray, np.ndarray]:
    """log10 probabilities of every place by single words and by the automaton.

    counts[m - 1] has the count of the m-gram that ends at a place, contexts[m - 2] that of its context.
    """
    base = (counts[0] + 1) / size
    p = base.copy()
    for m in range(2, len(counts) + 1):
        at, strength = np.flatnonzero(depth >= m - 1), strengths[min(m - 2, len(strengths) - 1)]
        p[at] = (counts[m - 1][at] + strength * p[at]) / (contexts[m - 2][at] + strength)
    return np.log10(base), np.log10(p)


def _score(order: int, ranges: int, total: int, distinct: int, trained: int, strengths: tuple[float, ...]):
    def run(block: pa.Table, answers: pa.Table) -> pa.Table:
        _, docs, held, sizes, packed = _fields(block, 0)
        depth, keys, of = _places(sizes, packed, order)
        every = np.concatenate([k[x] for k, x in zip(keys, of, strict=True)])
        by = np.argsort(every)
        ranked = every[by]
        new = np.r_[True, ranked[1:] != ranked[:-1]]
        which = np.empty(len(by), np.int32)
        which[by] = np.cumsum(new) - 1
        taught = (~held)[np.cumsum(depth == 0) - 1]
        mine, taught_times = _distinct(ranked, np.concatenate([taught[x] for x in of])[by])
        del every, by, ranked, keys, new
        asked = as_question(mine, taught_times, ranges)[0]
        answers = answers.sort_by("range")
        n = answers.column("n").to_numpy()
        planes = _unzip(answers.column("low"), 2 * n.astype(np.int64))
        each = np.repeat(np.cumsum(n, dtype=np.int64) - n, n) + np.arange(n.sum())
        low = planes[each].astype(np.int64) + 256 * planes[each + np.repeat(n, n)].astype(np.int64)
        if len(low) != len(asked):
            raise ValueError("a block's answer doesn't fit its question")
        got = low
        many = answers.column("at").combine_chunks()
        at = np.repeat(np.cumsum(n, dtype=np.int64) - n, np.diff(many.offsets.to_numpy()))
        got[at + many.flatten().to_numpy()] = answers.column("high").combine_chunks().flatten().to_numpy()
        got = got[np.searchsorted(asked, mine)][which]
        counts, past = [], 0
        for x in of:
            c = np.zeros(len(depth), np.int64)
            c[x] = got[past : past + len(x)]
            past += len(x)
            counts.append(c)
        # A text's mark is no token: as a context it was seen once in each training text.
        start = depth == 0
        contexts = [np.r_[0, np.where(start, trained, c)[:-1] if m == 0 else c[:-1]] for m, c in enumerate(counts[:-1])]
        base, score = traverse(depth, counts, contexts, float(total + distinct + 1), strengths)
        first = np.flatnonzero(start)
        size = np.diff(np.r_[first, len(depth)]) - 1
        known = np.add.reduceat((counts[0] > 0) & ~start, first, dtype=np.int64)
        sums = [np.add.reduceat(np.where(start, 0.0, x), first) for x in (base, score)]
        return pa.Table.from_arrays([docs, pa.array(held), pa.array(size), pa.array(known), pa.array(np.full(len(size), total)), *map(pa.array, sums)], _SCORE_NAMES)

    return run


def lm_scores(docs: DataFrame, held_out: Column, id_col: str = "doc_id", text_col: str = "text", order: int = ORDER, strengths: tuple[float, ...] = STRENGTHS, block_bytes: int = BLOCK_BYTES, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """(doc, held_out, n_tokens, n_known, train_tokens, base_score, score) for every row; held-out rows are not learnt from.

    A null text is empty: its only token is the end. A null ``held_out`` counts as false. Repeated rows are learnt from
    and scored each. With no training rows every token is unseen. An empty table gives no rows; other columns are not
    looked at.
    """
    ship_package(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).cast("string").alias("text"), F.coalesce(held_out, F.lit(False)).alias("held_out"))
    size, trained = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0).cast("long")), F.count_if(~F.col("held_out"))).first()
    ranges = max(1, math.ceil(size / range_bytes))
    total, distinct = vocabulary(rows.where("not held_out").select("text"), ranges)
    parts = max(ranges, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    blocks = rows.mapInArrow(_pack(block_bytes), BLOCKS).repartition(parts, "block")
    asked = blocks.mapInArrow(_ask(order, ranges), ASKED)
    answers = asked.repartition(parts, "range").groupBy("range").applyInArrow(_answer(ranges), ANSWERS)
    return blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(_score(order, ranges, total, distinct, trained, strengths), SCORES)


def op9_lm_scoring(spark, sf_dir: str) -> DataFrame:
    """Every document scored by a model of the documents that are not held out."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    held = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(7)) == 2
    return lm_scores(docs, held).withColumnRenamed("doc", "doc_id")
