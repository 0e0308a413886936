import re
from collections import Counter

from pyspark.sql import functions as F

from sift.llm import quality


def plain(text):
    t = text or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams = [tuple(w[i : i + 8]) for i in range(len(w) - 7)]
    c = Counter(grams)
    hit = set()
    for i, g in enumerate(grams):
        if c[g] > 1:
            hit.update(range(i, i + 8))
    failed = len(w) < 20 or 100 * len(hit) > 30 * len(w)
    return (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(hit), failed)


def base(r):
    return (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed)


def test_whole_table(spark, small):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    got = quality.op1_quality_rules(spark, small).collect()
    assert sorted(r.doc_id for r in got) == sorted(docs)
    for r in got:
        assert base(r) == plain(docs[r.doc_id]), r.doc_id
        assert r.kept == (not r.base_failed and r.rule == 0)
    label = {r.doc_id: r.quality for r in spark.read.parquet(f"{small}/labels.parquet").collect()}
    kept_good = [r.kept for r in got if label.get(r.doc_id) == 1 and not r.base_failed]
    assert sum(kept_good) >= 0.97 * len(kept_good)


def test_edges(spark):
    texts = [None, "", " \t\n\x0b\x0c\r", "one", "a b c d e f g h", "a b c d e f g h " * 2, "a b c d e f g h a b c d e f g", "x " * 40000, "é # * é\n\nl\nl\n l\n \n \n𝒳", "<<>>\r\n" * 30, " ".join(map(str, range(3000)))]
    df = spark.createDataFrame([(k, t, 1.5, 7) for k, t in enumerate(texts)], "doc_id long, text string, n_words double, rule int")
    got = {r.doc_id: r._quality for r in quality.judged(df, []).collect()}
    for k, t in enumerate(texts):
        assert base(got[k]) == plain(t), (k, got[k], plain(t))
    assert quality.judged(df.limit(0), []).collect() == []


def test_learning():
    rows = []
    for k in range(300):
        bad = k % 3 == 0
        x = {f: 0.0 for f in quality.FEATURES} | {"symbols_per_word": 0.5 + (k % 7) / 10 if bad else (k % 5) / 20, "n_words": float(k)}
        rows.append((x, bad, k // 3 % 3))
    rules = quality.learn(rows)
    assert [(c.feature, c.above) for c in rules[0]] == [("symbols_per_word", True)]
    assert quality.learn([]) == [] and quality.learn([(rows[0][0], True, 0)]) == []


def test_no_labels(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    labels = spark.createDataFrame([(None, 1), (3, None)], "doc_id long, quality int")
    assert quality.learn_from(docs, labels) == []


def test_held_out_labels(spark, small):
    """Rules learnt from a part of the labels catch the bad texts of the rest, and leave its good ones."""
    docs, labels = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("documents", "labels"))
    taught = labels.where("doc_id is not null and quality is not null").orderBy(F.xxhash64("doc_id"), "doc_id").limit(270).persist()
    rules = quality.learn_from(docs, taught)
    rest = labels.where("quality is not null").join(taught.select("doc_id"), "doc_id", "left_anti")
    judged = quality.judged(docs.select("doc_id", "text"), rules).join(rest, "doc_id").where("not _quality.base_failed").select("quality", "_quality.kept").collect()
    taught.unpersist()
    bad, good = ([r.kept for r in judged if r.quality == q] for q in (0, 1))
    assert len(bad) >= 4 and len(good) >= 80
    assert sum(bad) <= 0.2 * len(bad) and sum(good) >= 0.97 * len(good)
