import random

import numpy as np

from sift.llm import licenses
from sift.llm.decontam import words_of


def plain_lcs(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        prev = 0
        for j, y in enumerate(b, 1):
            prev, row[j] = row[j], prev + 1 if x == y else max(row[j], row[j - 1])
    return row[-1]


def test_align_equals_full_alignment_inside_the_band():
    rnd = random.Random(1)
    for _ in range(60):
        a = [rnd.choice([b"a", b"b", b"c", b"d"]) for _ in range(rnd.randrange(1, 12))]
        b = [rnd.choice([b"a", b"b", b"c", b"d"]) for _ in range(rnd.randrange(1, 12))]
        matched, first, last = licenses.align(a, b, 0, 50)
        assert matched == plain_lcs(a, b)
        if matched:
            assert plain_lcs(a, b[first:last]) == matched


def test_winnow_guarantee():
    rnd = np.random.default_rng(2)
    for n in (1, 2, 5, 40):
        h = rnd.integers(0, 50, n).astype(np.uint64)
        kept = licenses.winnow(h, 4)
        assert all(any(a <= k < a + 4 for k in kept) for a in range(max(1, n - 3)))
    assert licenses.winnow(np.zeros(0, np.uint64), 4) == []


def test_templates_and_edits(spark):
    rows, want = [], {}
    for k, (name, text) in enumerate(licenses.TEMPLATES):
        words = text.split()
        cut = words[: len(words) // 2] + ["indeed"] + words[len(words) // 2 :]
        rows += [(3 * k, "before it. " + text.upper() + "\nafter"), (3 * k + 1, "é x " + " ".join(cut)), (3 * k + 2, " ".join(words[: len(words) // 3]))]
        want[3 * k] = want[3 * k + 1] = name
    rows += [(90, None), (91, ""), (None, licenses.TEMPLATES[0][1]), (92, "Licensed under the law of the land"), (93, "word " * 50000 + licenses.TEMPLATES[1][1]), (93, licenses.TEMPLATES[1][1])]
    df = spark.createDataFrame([(d, t, "MIT", 1) for d, t in rows], "doc_id long, text string, license string, start int")
    got = licenses.license_spans(df).collect()
    by = {}
    for r in got:
        by.setdefault(r.doc, []).append(r)
    text = dict(rows)
    for d, name in want.items():
        assert name in [r.license for r in by[d]], (d, name)
        for r in by[d]:
            span = words_of(text[d].encode()[r.start : r.end].decode())
            template = words_of(dict(licenses.TEMPLATES)[r.license])
            assert plain_lcs(template, span) == r.matched and r.words == len(template)
    assert len(by[93]) == 2 and len(by[None]) == 1
    assert not {d for d in by if d is not None and d % 3 == 2 and d < 27} and 92 not in by and 90 not in by
    assert licenses.license_spans(df.limit(0)).collect() == [] and licenses.license_spans(df, ()).collect() == []


def test_whole_table(spark, small):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    got = {(r.doc_id, r.license) for r in licenses.op4_license_scans(spark, small).collect()}
    for d, t in docs.items():
        for name, line in licenses.TEMPLATES[:4]:
            assert not line.lower() in t.lower() or (d, name) in got


def test_edits_that_leave_no_run_of_words(spark):
    """Every choice of words that the least coverage lets be other ones, the words standing apart, and notices side by side."""
    import itertools

    rows = []
    for name, text in licenses.TEMPLATES[:6]:
        words = text.split()
        n = len(words_of(text))
        if n == len(words):
            rows += [(name, n - gone, " ".join("other" if k in at else w for k, w in enumerate(words))) for gone in range(n // 5 + 1) for at in itertools.combinations(range(n), gone)]
    rows += [("MIT", 5, "Released it under it the it MIT it License"), ("MIT", 4, "Released under an MIT License"), ("pair", 2, "a short one"), ("one", 1, "the single here")]
    df = spark.createDataFrame([(k, t) for k, (_, _, t) in enumerate(rows)], "doc_id long, text string").coalesce(2)
    got = {(r.doc, r.license, r.matched) for r in licenses.license_spans(df, (*licenses.TEMPLATES, ("pair", "short one"), ("one", "single"))).collect()}
    for k, (name, matched, t) in enumerate(rows):
        assert (k, name, matched) in got, t
    line = licenses.TEMPLATES[1][1] + "\n"
    twice = licenses.license_spans(spark.createDataFrame([(1, line * 3)], "doc_id long, text string")).collect()
    assert sorted((r.start, r.matched) for r in twice if r.license == "MIT") == [(k * len(line), 5) for k in range(3)]


def test_brute_force(spark):
    """Lost heads and tails, inserted and exchanged words: each place where enough words are matched is reported once, nothing else is."""
    rnd = random.Random(12)
    templates = [(f"T{k}", " ".join(f"t{k}w{rnd.randrange(40)}" for _ in range(n))) for k, n in enumerate((5, 9, 20, 20, 34))]
    texts = []
    for name, text in templates:
        w = text.split()
        for lost in range(len(w) // 5 + 1):
            for at in (len(w) // 2, len(w) - 2):
                texts.append(" ".join(["x"] * 10 + w[lost:at] + ["inserted"] + w[at:] + ["y"] * 5))
                texts.append(" ".join(["x"] * 3 + w[: len(w) - lost] + ["z"] * 12 + w[lost:]))
    for _ in range(150):
        parts = []
        for _ in range(rnd.randrange(1, 4)):
            w = rnd.choice(templates)[1].split()
            for _ in range(rnd.randrange(0, 5)):
                k = rnd.randrange(len(w))
                w[k : k + rnd.randrange(2)] = [rnd.choice(["odd", "even"])]
            parts += w + [f"f{rnd.randrange(9)}" for _ in range(rnd.randrange(30))]
        texts.append(" ".join(parts))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {}
    for r in licenses.license_spans(df, templates).collect():
        got.setdefault((r.doc, r.license), []).append(r)
    for d, t in enumerate(texts):
        words = words_of(t)
        for name, text in templates:
            template = words_of(text)
            n = len(template)
            spans = sorted((r.start, r.end) for r in got.get((d, name), []))
            assert all(a[1] <= b[0] for a, b in zip(spans, spans[1:], strict=False)), (name, t)
            for r in got.get((d, name), []):
                assert 5 * r.matched >= 4 * n and r.words == n and plain_lcs(template, words_of(t[r.start : r.end])) == r.matched
            # A window of the template's length that holds enough of it touches a reported span.
            at = np.cumsum([0, *(len(x) + 1 for x in t.split())])
            for k in range(max(1, len(words) - n + 1)):
                if 5 * plain_lcs(template, words[k : k + n]) >= 4 * n:
                    assert any(a < at[min(k + n, len(words))] and at[k] < b for a, b in spans), (name, k, t)
