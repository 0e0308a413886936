import base64

import public_tokenizers as P
import pytest
import tiktoken

from sift.llm import tokencounts

PATH = P.path("byte_bpe_50k.tiktoken")


def plain(text, rule):
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(PATH, "rb"))}
    enc = tiktoken.Encoding("t", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    raw = (text or "").encode()
    starts = [0] + [i + 1 for i, b in enumerate(raw) if b == 10 and i + 1 < len(raw)]
    ends = [*starts[1:], len(raw)]
    got, cross, at = [0.0] * len(starts), [0] * len(starts), 0
    for t in enc.encode_ordinary(text or ""):
        n = len(enc.decode_single_token_bytes(t))
        inside = [max(0, min(at + n, e) - max(at, s)) for s, e in zip(starts, ends, strict=True)]
        over = [k for k, x in enumerate(inside) if x]
        for k in over[1:]:
            cross[k] += 1
        if rule == "share":
            for k in over:
                got[k] += inside[k] / n
        else:
            got[over[0] if rule == "start" else max(over, key=lambda k: (inside[k], -k))] += 1
        at += n
    assert at == len(raw)
    return [(k, s, e, round(g, 9), c) for k, (s, e, g, c) in enumerate(zip(starts, ends, got, cross, strict=True))]


@pytest.mark.parametrize("rule", tokencounts.RULES)
def test_brute_force(spark, rule, tiny):
    texts = [(1, None), (2, ""), (3, "\n"), (4, "\n\n\n\n\n\na\n\n  b\n"), (5, "É𝒳\n <|endoftext|>\n\tx"), (5, "É𝒳"), (None, "a\n b"), (6, "line of words\n" * 2000)]
    texts += [(r.doc_id + 100, r.text) for r in spark.read.parquet(f"{tiny}/documents.parquet").where("doc_id < 30").collect()]
    df = spark.createDataFrame([(d, t, 1, 2) for d, t in texts], "doc_id long, text string, section int, doc int")
    got = tokencounts.section_tokens(df, PATH, P.PATTERN, rule=rule).collect()
    want = [(d, *x) for d, t in texts for x in plain(t, rule)]
    assert sorted(((r.doc, r.section, r.start_byte, r.end_byte, round(r.n_tokens, 9), r.n_crossing) for r in got), key=str) == sorted(want, key=str)
    assert tokencounts.section_tokens(df.limit(0), PATH, P.PATTERN, rule=rule).collect() == []


def test_whole_table(spark, tiny):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    got = {}
    for r in tokencounts.op8_token_counts(spark, tiny).collect():
        got.setdefault(r.doc_id, []).append((r.section, r.start_byte, r.end_byte, float(r.n_tokens), r.n_crossing))
    assert sorted(got) == sorted(docs)
    for d in list(docs)[:40]:
        assert sorted(got[d]) == plain(docs[d], "start")
