import random

import pytest

from sift.llm import decontam

from .helpers import same_as_sql


def brute(docs, bench):
    wins = {}
    for i, t in bench:
        w = decontam.words_of(t)
        m = min(13, len(w))
        for k in range(len(w) - m + 1 if w else 0):
            wins.setdefault(tuple(w[k : k + m]), set()).add(i)
    sizes = {len(w) for w in wins}
    out = []
    for d, t in docs:
        w = decontam.words_of(t)
        hit, items = set(), set()
        for m in sizes:
            for k in range(len(w) - m + 1):
                if tuple(w[k : k + m]) in wins:
                    hit.update(range(k, k + m))
                    items |= wins[tuple(w[k : k + m])]
        out.append((d, len(w), len(hit), sorted(str(i) for i in items if i is not None)))
    return sorted(out, key=str)


def found(spark, docs, bench, **kw):
    d = spark.createDataFrame([(i, t, 1, "z") for i, t in docs], "doc_id long, text string, item_id int, _spans string")
    b = spark.createDataFrame(bench, "item_id string, text string")
    got = decontam.contamination(d, b, carry=["doc_id"], **kw).select("doc_id", "contamination.*").collect()
    for r in got:
        assert r.contaminated == (r.n_hit > 0 and 20 * r.n_hit >= r.n_words)
    return sorted(((r.doc_id, r.n_words, r.n_hit, r["items"]) for r in got), key=str)


@pytest.mark.parametrize("block", [1 << 20, 400])
def test_brute_force(spark, block):
    rnd = random.Random(5)
    vocab = [f"w{k}" for k in range(12)] + ["É", "longlonglongword1x2y3z", "longlonglongwordAx2y3z"]
    say = lambda n: " ".join(rnd.choice(vocab) for _ in range(n))
    bench = [(str(k), say(rnd.choice([1, 2, 3, 12, 13, 14, 30]) if k > 4 else 20)) for k in range(12)] + [(None, say(15)), ("n", None), ("e", " ,"), ("0", say(16))]
    docs = [(k, say(rnd.randrange(300))) for k in range(40)] + [(90, None), (91, ""), (91, ""), (None, bench[0][1])]
    docs += [(100 + k, say(30) + ", " + b[1].upper().replace(" ", "--") + ". " + say(40)) for k, b in enumerate(bench) if b[1]]
    docs.append((999, say(60000)))
    assert found(spark, docs, bench, block_bytes=block) == brute(docs, bench)


def test_empty(spark):
    assert found(spark, [], [("1", "a b")]) == []
    assert found(spark, [(1, "a b c")], []) == [(1, 3, 0, [])]


def test_same_as_sql(spark, small):
    same_as_sql(decontam.op5_benchmark_decontamination(spark, small), decontam.ORACLE, small)
