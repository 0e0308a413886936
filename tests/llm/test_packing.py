import zlib

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from sift.llm import packing

PATH = public_tokenizers.path("word_bpe_49k.json")


def check(rows, texts):
    """Exact round trip: every document's pieces in order, ids by the plain tokenizer, sequences gapless and within capacity."""
    tk = Tokenizer.from_file(PATH)
    want = []
    for d, t in texts:
        ids = tk.encode(t or "", add_special_tokens=False).ids + [0]
        for k, s in enumerate(range(0, len(ids), 2048)):
            p = ids[s : s + 2048]
            want.append((d, k, s, len(p), zlib.crc32(np.array(p, "<u4").tobytes())))
    assert sorted(((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows), key=str) == sorted(want, key=str)
    seqs = {}
    for r in rows:
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for ps in seqs.values():
        at = 0
        for o, n in sorted(ps):
            assert o == at
            at += n
        assert at <= 2048
    return len(seqs), sum(w[3] for w in want)


def test_whole_table(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = packing.op3_best_fit_packing(spark, small).collect()
    n, total = check(rows, [(r.doc_id, r.text) for r in docs.collect()])
    assert n <= 1.01 * total / 2048 + 1


def test_edges(spark):
    schema = "doc_id long, text string, bin long, place string, length int"
    texts = [(1, None), (2, ""), (None, "null id"), (3, "same"), (3, "same"), (4, "a b\x1cc <|endoftext|> Σας ΣΑΣ é"), (5, "word " * 30000), (6, "x" * 9000)]
    df = spark.createDataFrame([(d, t, 1, "p", 2) for d, t in texts], schema)
    check(packing.contract_rows(df, PATH).collect(), texts)
    assert packing.contract_rows(df.limit(0), PATH).collect() == []


def test_tree_levels(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    pieces = packing.materialise(packing.cut_pieces(docs, PATH), "t")
    rows = packing.pack_pieces(pieces, task_pieces=10, fan_in=3, hosts=4).collect()
    assert len(rows) == pieces.count()
    fill = {}
    for r in rows:
        fill.setdefault(r.bin, []).append((r.place, r.length))
    for ps in fill.values():
        ends = [o + n for o, n in sorted(ps)]
        assert [o for o, _ in sorted(ps)] == [0, *ends[:-1]] and ends[-1] <= 2048


def test_sequences_hold_the_ids(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    total, held = 0, {}
    for r in packing.sequences(docs, PATH).collect():
        whole = np.array(r.ids, "<u4")
        for d in r.docs:
            held[d.doc] = held.get(d.doc, []) + [(d.piece, whole[d.place : d.place + d.length].tolist())]
        assert len(r.ids) == sum(d.length for d in r.docs)
        total += len(r.ids)
    assert total == packing.cut_pieces(docs, PATH).groupBy().sum("length").first()[0]
    tk = Tokenizer.from_file(PATH)
    for r in docs.collect():
        assert sum((ids for _, ids in sorted(held[r.doc_id])), []) == tk.encode(r.text or "", add_special_tokens=False).ids + [0]


def test_odd_words():
    """Words of every class, alone and in texts, have the ids of the plain tokenizer; so they have from a nearly full cache."""
    import random

    import pyarrow as pa

    rng = random.Random(5)
    letters = ["a", "Z", "the", "É", "ß", "Ö", "÷", "×", "ÿ", "ñ", "'", "'s", "'ll", "I", "1", "23", "²", "<", "|", "<|endoftext|>", "<|ENDOFTEXT|>", "=", "--", "_", "İ", "Σ", "e\u0301", "A\u030a", "中", "🙂", "\x1c", "\u00a0", "\u2003", "\x85", "\x00", "fi", "ǅ", "x" * 40]
    texts = [None, "", " \n"] + ["".join(rng.choice(letters + [" "] * 8) for _ in range(rng.randrange(1, 40))) for _ in range(3000)]
    tk, coder = Tokenizer.from_file(PATH), packing.WordEncoder(PATH)
    for lot in range(0, len(texts), 300):
        some = texts[lot : lot + 300]
        ids, first = coder.encode(pa.array(some, pa.string()))
        for k, t in enumerate(some):
            assert ids[first[k] : first[k + 1]].tolist() == tk.encode(t or "", add_special_tokens=False).ids, t
