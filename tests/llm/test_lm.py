import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from sift.llm import lm


def test_whole_table(spark, small):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    got = lm.op9_lm_scoring(spark, small).collect()
    held = {d: zlib.crc32(str(d).encode()) % 7 == 2 for d in docs}
    c = Counter(w for d, t in docs.items() if not held[d] for w in lm.tokens_of(t))
    n, v = c.total(), len(c)
    assert sorted(r.doc_id for r in got) == sorted(docs)
    for r in got:
        tokens = lm.tokens_of(docs[r.doc_id])
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[r.doc_id], len(tokens), sum(c[w] > 0 for w in tokens), n)
        assert math.isclose(r.base_score, math.fsum(math.log10((c[w] + 1) / (n + v + 1)) for w in tokens), rel_tol=1e-9)
    # Held-out accuracy: the automaton predicts unseen texts better than single words do.
    assert sum(r.score for r in got if r.held_out) > sum(r.base_score for r in got if r.held_out)


def plain_model(train, order, strengths=lm.STRENGTHS):
    """Probabilities by the definition: counts of all n-grams, recursion over contexts."""
    grams, after = Counter(), Counter()
    for t in train:
        seq = [b"", *lm.tokens_of(t)]
        for m in range(1, order + 1):
            for i in range(m == 1, len(seq) - m + 1):
                grams[tuple(seq[i : i + m])] += 1
                after[tuple(seq[i : i + m - 1])] += 1
    n, v = sum(x for g, x in grams.items() if len(g) == 1), sum(len(g) == 1 for g in grams)

    def p(h, w):
        if not h:
            return (grams[(w,)] + 1) / (n + v + 1)
        s = strengths[min(len(h), len(strengths)) - 1]
        return (grams[(*h, w)] + s * p(h[1:], w)) / (after[h] + s)

    return p, [g[0] for g in grams if len(g) == 1]


@pytest.mark.parametrize("block_bytes, range_bytes", [(8 << 20, 8 << 20), (3000, 2000)])
def test_brute_force(spark, block_bytes, range_bytes):
    rnd = random.Random(2)
    texts = [(k, " ".join(rnd.choices("the The a of cat sat É x y".split(), weights=[9, 3, 5, 5, 4, 3, 2, 1, 1], k=rnd.randrange(1, 40)))) for k in range(60)]
    texts += [(70, None), (71, ""), (71, ""), (None, "the cat sat of unseenword"), (72, "the cat " * 5000), (73, "  zzz\tqqq "), (74, " ".join(f"w{rnd.randrange(900)}" for _ in range(700)))]
    df = spark.createDataFrame([(d, t, True, 5) for d, t in texts], "doc_id long, text string, held_out boolean, block int")
    held = F.col("doc_id") % 5 == 1
    train = [t for d, t in texts if d is None or d % 5 != 1]
    for order in (1, 2, 3, 4):
        p, vocab = plain_model(train, order)
        got = lm.lm_scores(df, held, order=order, block_bytes=block_bytes, range_bytes=range_bytes).collect()
        want = []
        for d, t in texts:
            seq, s = [b"", *lm.tokens_of(t)], 0.0
            for i in range(1, len(seq)):
                s += math.log10(p(tuple(seq[max(0, i - order + 1) : i]), seq[i]))
            want.append((str(d), len(seq) - 1, round(s, 6)))
        assert sorted((str(r.doc), r.n_tokens, round(r.score, 6)) for r in got) == sorted(want)
        for h in ((), (b"the",), (b"the", b"cat"), (b"",)):
            h = h[-(order - 1) :] if order > 1 else ()
            assert math.isclose(sum(p(h, w) for w in vocab) + p(h, b"never-seen"), 1, rel_tol=1e-9)


def test_questions():
    """Keys survive the way there, with repeated and bridging ones; what is counted adds up."""
    rng = np.random.default_rng(3)
    for n, ranges, most in ((1, 1, 3), (5, 7, 1000), (3000, 3, 700), (400_000, 5, 2), (50, 1 << 20, 300)):
        keys = np.unique(rng.integers(0, 1 << lm.DIGEST_BITS, n, dtype=np.uint64))
        counts = rng.integers(0, most, len(keys))
        asked, width, gaps, low, bounds = lm.as_question(keys, counts, ranges)
        size = np.diff(bounds)
        width_of = (1 << lm.DIGEST_BITS) // ranges + 1
        some = np.flatnonzero(size)
        back = lm.asked_keys((some * width_of).astype(np.uint64), gaps, size[some], width)
        assert (back == asked).all() and (np.sort(asked) == asked).all() and (np.isin(keys, asked)).all()
        at = np.searchsorted(keys, asked)
        real = (at < len(keys)) & (keys[np.minimum(at, len(keys) - 1)] == asked)
        assert low[~real].sum() == 0 and (np.bincount(at[real], low[real], len(keys)) == counts).all()
        assert len(gaps) <= 1.2 * 8 * len(keys) + low.sum() // 200 * 8 + 8


def test_digests_tell_words_apart():
    import pyarrow as pa

    from sift.llm.textbatch import IS_SOLID, flat, word_bounds, word_digests

    rnd = random.Random(1)
    words = list({"".join(rnd.choice("ab") for _ in range(rnd.choice([1, 5, 8, 9, 16, 17, 24, 40, 100]))) for _ in range(20_000)} | {"c" * 5000, "c" * 5001, "c" * 2500 + "d" + "c" * 2499, "a" * 20 + "b" + "a" * 20, "a" * 41})
    buf, offsets = flat(pa.array([" ".join(words), " ".join(reversed(words))]))
    starts, ends, first = word_bounds(buf, offsets, IS_SOLID)
    for seed in (0, 1):
        got = word_digests(buf, starts, ends, seed)
        assert len(set(got.tolist())) == len(words) and (got[: first[1]] == got[first[1] :][::-1]).all()


def test_nothing_to_learn_from(spark):
    df = spark.createDataFrame([(1, "a b"), (2, None)], "doc_id long, text string")
    assert lm.lm_scores(df.limit(0), F.lit(False)).collect() == []
    got = lm.lm_scores(df, F.lit(True)).collect()
    assert sorted((r.doc, r.n_tokens, r.n_known, r.train_tokens, r.base_score, r.score) for r in got) == [(1, 3, 0, 0, 0.0, 0.0), (2, 1, 0, 0, 0.0, 0.0)]
