"""Arrow batches of texts as flat byte buffers, cut into slices of bounded size."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text handled at once by the vectorised operators.
SLICE_BYTES = 8 << 20

ASCII_LOWER = np.arange(256, dtype=np.uint8)
ASCII_LOWER[65:91] += 32


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Row slices of a batch whose texts add up to about ``limit`` bytes; a longer single text is a slice of its own."""
    if not batch.num_rows:
        return
    text = batch.column(column)
    sizes = np.asarray(pc.fill_null(pc.binary_length(text), 0), dtype=np.int64)
    label = np.cumsum(sizes) // limit
    cuts = np.flatnonzero(np.diff(label)) + 1
    for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), batch.num_rows], strict=True):
        yield batch.slice(a, b - a)


def flat(text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All texts in one uint8 buffer and the len+1 offsets into it; a null counts as empty."""
    if text.null_count:
        text = pc.fill_null(text, b"" if pa.types.is_binary(text.type) else "")
    wide = pa.types.is_large_string(text.type)
    offsets = np.frombuffer(text.buffers()[1], np.int64 if wide else np.int32)[text.offset : text.offset + len(text) + 1].astype(np.int64)
    data = text.buffers()[2]
    buf = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return buf[offsets[0] : offsets[-1]], offsets - offsets[0]


#: Bytes that are not ASCII white space.
IS_SOLID = np.ones(256, bool)
IS_SOLID[[9, 10, 11, 12, 13, 32]] = False


def word_bounds(buf: np.ndarray, offsets: np.ndarray, is_word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte starts and ends of maximal runs of word bytes, and for each text the index of its first word (len+1)."""
    if not buf.size:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(offsets), np.int64)
    inside = is_word[buf]
    before = np.empty_like(inside)
    before[0] = False
    before[1:] = inside[:-1]
    after = np.empty_like(inside)
    after[-1] = False
    after[:-1] = inside[1:]
    edge = offsets[(offsets > 0) & (offsets < buf.size)]
    before[edge] = False
    after[edge - 1] = False
    starts = np.flatnonzero(inside & ~before)
    ends = np.flatnonzero(inside & ~after) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def spread(at: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Indices at[0], at[0] + 1, ... (n[0] of them), at[1], ..."""
    return np.repeat(at - (np.cumsum(n) - n), n) + np.arange(n.sum())


_MASK = np.array([(1 << (8 * n)) - 1 for n in range(8)] + [2**64 - 1], dtype=np.uint64)
_C1, _C2, _C3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)


def word_keys(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit key of each word from its length, first and last eight bytes. Equal words have equal keys; equal keys are to be confirmed."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    padded = np.zeros(buf.size + 16, np.uint8)
    padded[8 : 8 + buf.size] = buf
    words = np.ndarray((buf.size + 9,), "<u8", padded, strides=(1,))
    size = ends - starts
    key = (words[starts + 8] & _MASK[np.minimum(size, 8)]) * _C1
    key ^= np.where(size >= 8, words[ends], np.uint64(0)) * _C2
    key ^= size.astype(np.uint64) * _C3
    key ^= key >> np.uint64(29)
    key *= _C2
    return key ^ (key >> np.uint64(32))


def _stirred(h: np.ndarray) -> np.ndarray:
    """One-to-one scrambling of 64-bit values, in place."""
    h ^= h >> np.uint64(32)
    h *= _C1
    h ^= h >> np.uint64(29)
    h *= _C2
    h ^= h >> np.uint64(32)
    return h


#: Words of more bytes are hashed one by one.
_GIANT = 4096


def word_digests(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int = 0) -> np.ndarray:
    """A 64-bit digest of all bytes of each word; digests by other seeds are independent."""
    size = ends - starts
    h = size.astype(np.uint64) * _C3
    h += np.uint64((seed * 0xA0761D6478BD642F + 0x2545F4914F6CDD1D) & (2**64 - 1))
    if not len(starts):
        return h
    padded = np.zeros(buf.size + 16, np.uint8)
    padded[8 : 8 + buf.size] = buf
    eight = np.ndarray((buf.size + 9,), "<u8", padded, strides=(1,))
    h ^= eight[starts + 8] & _MASK[np.minimum(size, 8)]
    h = _stirred(h)
    some = np.flatnonzero(size > 8)
    if some.size:
        h[some] = _stirred(h[some] ^ eight[ends[some]])
        some = some[size[some] <= _GIANT]
        for k in range(8, _GIANT, 8):  # what lies between the first and the last eight bytes
            some = some[size[some] - 8 > k]
            if not some.size:
                break
            h[some] = _stirred(h[some] ^ eight[starts[some] + 8 + k])
        giant = np.flatnonzero(size > _GIANT)
        if giant.size:
            import xxhash

            h[giant] ^= np.array([xxhash.xxh3_64_intdigest(buf[starts[i] : ends[i]].tobytes(), seed) for i in giant], np.uint64)
    return h
