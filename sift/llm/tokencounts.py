"""Token counts by section, from one encoding of the whole document.

A byte-level tokenizer is lossless: the tokens' byte lengths, summed up, are the tokens' spans in the document, without
gap or overlap. Sections are byte spans too, and the two are joined as intervals by binary search. A token that lies in
several sections goes where the rule says: ``start``, to the section of its first byte; ``most``, to the section that
has most of its bytes (the earlier on a tie); ``share``, to every one by its share of bytes.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sift.llm.textbatch import slices
from sift.runtime import ship_package

RULES = ("start", "most", "share")

_coders: dict[str, tuple] = {}


def coder(path: str, pattern: str):
    """This worker's encoding of a rank file, and the byte length of each token."""
    if path not in _coders:
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        sizes = np.zeros(max(ranks.values()) + 1, np.int64)
        for token, rank in ranks.items():
            sizes[rank] = len(token)
        _coders[path] = tiktoken.Encoding("public", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}), sizes
    return _coders[path]


def sections_of(raw: bytes, size: int) -> np.ndarray:
    """Starts of a text's sections: a section is a line with its break; an empty text has one empty section."""
    at = np.flatnonzero(np.frombuffer(raw, np.uint8) == 10) + 1
    return np.concatenate([[0], at[at < size]])


def allocate(token_ends: np.ndarray, section_starts: np.ndarray, size: int, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """For each section its tokens by the rule (a float), and how many tokens cross its start."""
    n = len(section_starts)
    got, crossing = np.zeros(n), np.zeros(n, np.int64)
    if not len(token_ends):
        return got, crossing
    token_starts = np.concatenate([[0], token_ends[:-1]])
    first = np.searchsorted(section_starts, token_starts, side="right") - 1
    last = np.searchsorted(section_starts, token_ends - 1, side="right") - 1
    whole = first == last
    got += np.bincount(first[whole], minlength=n)
    bounds = np.concatenate([section_starts, [size]])
    for t in np.flatnonzero(~whole).tolist():
        a, b = token_starts[t], token_ends[t]
        over = np.arange(first[t], last[t] + 1)
        inside = np.minimum(b, bounds[over + 1]) - np.maximum(a, bounds[over])
        crossing[over[1:]] += 1
        if rule == "share":
            got[over] += inside / (b - a)
        else:
            got[over[0] if rule == "start" else over[int(np.argmax(inside))]] += 1
    return got, crossing


COUNTS = "doc long, section int, start_byte long, end_byte long, n_tokens double, n_crossing long"


def _count(path: str, pattern: str, rule: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoding, sizes = coder(path, pattern)
        kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.int64())
        names = ("doc", "section", "start_byte", "end_byte", "n_tokens", "n_crossing")
        for batch in batches:
            for part in slices(batch, "text"):
                docs, cols, many = [], [[] for _ in range(5)], []
                for doc, text in zip(part.column("doc").to_pylist(), part.column("text").to_pylist(), strict=True):
                    raw = (text or "").encode()
                    ids = encoding.encode_to_numpy(text or "", disallowed_special=())
                    starts = sections_of(raw, len(raw))
                    got, crossing = allocate(np.cumsum(sizes[ids]), starts, len(raw), rule)
                    docs.append(doc)
                    many.append(len(starts))
                    for c, x in zip(cols, (np.arange(len(starts)), starts, np.append(starts[1:], len(raw)), got, crossing), strict=True):
                        c.append(x)
                owner = pa.array(docs, pa.int64()).take(pa.array(np.repeat(np.arange(len(docs)), many)))
                yield pa.RecordBatch.from_arrays([owner, *(pa.array(np.concatenate(c), k) for c, k in zip(cols, kinds[1:], strict=True))], names)

    return run


def section_tokens(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", rule: str = "start") -> DataFrame:
    """(doc, section, start_byte, end_byte, n_tokens, n_crossing): a row for every line of every document.

    n_tokens adds up to the tokens of the whole document under every rule; n_crossing counts tokens that begin before
    the section and reach into it. A null or empty text has one empty section. Repeated rows count each; an empty table
    gives no rows; other columns are not looked at.
    """
    if rule not in RULES:
        raise ValueError(f"rule is one of {', '.join(RULES)}")
    ship_package(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).cast("string").alias("text")).mapInArrow(_count(ranks_path, pattern, rule), COUNTS)


def op8_token_counts(spark, sf_dir: str) -> DataFrame:
    """Tokens of every line of every document; a token belongs to the line of its first byte."""
    import public_tokenizers

    found = section_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    return found.withColumn("n_tokens", F.col("n_tokens").cast("long")).withColumnRenamed("doc", "doc_id")
