import random

import numpy as np

from sift.llm import chunks


def test_rolling_hash_by_definition():
    buf = np.random.default_rng(3).integers(0, 256, 500, dtype=np.uint8)
    h, want = 0, []
    for b in buf.tolist():
        h = ((h << 1) + int(chunks._GEAR[b])) & 0xFFFF
        want.append(h)
    assert chunks.gear_hash(buf).tolist() == want
    assert chunks.gear_hash(np.zeros(0, np.uint8)).tolist() == []


def test_planted_passages(spark):
    """Passages of over 50 words are found in every document that holds them, wherever they stand; nothing else is."""
    rnd = random.Random(11)
    word = lambda: "".join(rnd.choice("abcdefghijklmnopqrstuvwxyzé") for _ in range(rnd.randrange(2, 9)))
    say = lambda n: " ".join(word() for _ in range(n))
    passages = [say(51) for _ in range(150)]
    rows, holds = [], {}
    for d in range(600):
        p = rnd.sample(range(150), 1) if d < 450 else []
        holds[d] = set(p)
        rows.append((d, say(rnd.randrange(5, 80)) + " " + " ".join(passages[k] + " " + say(10) for k in p)))
    shared = {d for d in holds for k in holds[d] if sum(k in holds[e] for e in holds) > 1}
    rows += [(900, None), (901, ""), (None, rows[0][1]), (902, "short"), (903, "x" * 100000)]
    df = spark.createDataFrame([(d, t, 1, "q") for d, t in rows], "doc_id long, text string, a int, digest string")
    got = chunks.repeated_passages(df).collect()
    assert {r.doc for r in got} == shared
    for r in got:
        assert holds[r.doc] & holds[r.other]
        raw = rows[r.doc][1].encode()
        (k,) = holds[r.doc]
        at = raw.index(passages[k].encode())
        assert r.start >= at - 40 and r.end <= at + len(passages[k].encode()) + 40
    assert chunks.repeated_passages(df.limit(0)).collect() == []


def test_insertion_moves_but_keeps_chunks(spark):
    rnd = random.Random(4)
    t = " ".join(str(rnd.random()) for _ in range(400))
    df = spark.createDataFrame([(1, t), (2, t[:3000] + "inserted" + t[3000:]), (2, "again " + t)], "doc_id long, text string")
    got = {(r.doc): r for r in chunks.repeated_passages(df).collect()}
    assert got[1].first and not got[2].first and got[1].other == 2 and got[2].other == 1
    n = chunks.chunks(df.where("doc_id = 1")).count()
    assert chunks.chunks(df.limit(2)).groupBy("digest").count().count() <= n + 8


def brute(rows, within=False, least=chunks.MIN_REPEAT):
    """(doc, start, end, first) by comparing the chunks' bytes."""
    cut = {}
    for d, t in rows:
        raw = np.frombuffer((t or "").encode(), np.uint8)
        edge = chunks.cuts(raw, np.array([0, len(raw)]))
        cut[d] = [(a, b, raw[a:b].tobytes()) for a, b in zip(edge, edge[1:], strict=False)]
    held = {}
    for d in sorted(cut):
        for a, _, c in cut[d]:
            held.setdefault(c, []).append((d, a))
    out = []
    for d in sorted(cut):
        rows_, last = [], None
        for a, b, c in cut[d]:
            if len(held[c]) > 1 if within else len({x for x, _ in held[c]}) > 1:
                if last != a:
                    rows_.append([])
                rows_[-1].append((a, b, held[c][0] == (d, a)))
                last = b
        for r in rows_:
            if r[-1][1] - r[0][0] >= least:
                parts = [[r[0]]]
                for x in r[1:]:
                    if x[2] == parts[-1][-1][2]:
                        parts[-1].append(x)
                    else:
                        parts.append([x])
                out += [(d, p[0][0], p[-1][1], p[0][2]) for p in parts]
    return sorted(out)


def test_brute_force_and_cut(spark):
    """Owners as by comparing bytes; after the cut every repeated passage is there exactly once."""
    rnd = random.Random(8)
    word = lambda: "".join(rnd.choice("abcdefghijklmnopqrstuvwxyzé中") for _ in range(rnd.randrange(2, 9)))
    say = lambda n: " ".join(word() for _ in range(n))
    p, q, r = say(60), say(70), say(80)
    texts = [f"{say(9)} {p} {say(9)}", f"{say(9)} {p} {q} {say(5)}", f"{p} {q} {say(30)} {q} {p}", f"{r} {say(9)} {r}", f"{say(4)} {r}", say(50), "", None]
    texts += [" ".join(rnd.choice([p, q, r, say(12)]) for _ in range(rnd.randrange(1, 6))) for _ in range(25)]
    rows = list(enumerate(texts))
    df = spark.createDataFrame([(d, t, "x", 1) for d, t in rows], "doc_id long, text string, _cut string, start int")
    for within in (False, True):
        got = chunks.repeated_passages(df, within=within).collect()
        assert sorted((x.doc, x.start, x.end, x.first) for x in got) == brute(rows, within)
        cut = chunks.without_repeats(df, within=within)
        assert cut.columns == df.columns
        left = {x.doc_id: x.text for x in cut.collect()}
        assert len(left) == len(rows) and left[6] == "" and left[7] is None and left[5] == texts[5]
        whole = "\n".join(left[d] or "" for d, _ in rows)
        for passage in (p, q, r):
            core = passage[60:-60]
            assert whole.count(core) == 1, (within, whole.count(core))
        before = {c for t in texts if t for c in t.split()}
        assert all(c in whole for c in before)
        again = spark.createDataFrame([(d, left[d]) for d, _ in rows], "doc_id long, text string")
        assert chunks.repeated_passages(again, within=within).where("not first").count() <= 2
    assert chunks.without_repeats(df.limit(0)).collect() == []
    twice = spark.createDataFrame([(1, p), (1, p), (2, p), (None, p)], "doc_id long, text string")
    assert sorted((str(x.doc_id), len(x.text) > 100) for x in chunks.without_repeats(twice).collect()) == [("1", True), ("1", True), ("2", False), ("None", True)]
