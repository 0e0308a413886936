import random

import corpus_pipeline
from pyspark.sql import functions as F
from sift.llm import decontam, quality, secrets

from .test_decontam import brute as brute_contamination
from .test_neardup import plain_components
from .test_packing import check as check_packed
from .test_quality import plain as plain_statistics


def test_whole_table_against_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = {r.doc_id: r.text for r in docs.collect()}
    rules = quality.learn_from(docs, spark.read.parquet(f"{small}/labels.parquet"))
    read = lambda x, f: {"symbols_per_word": x[2] / max(x[0], 1)}[f]
    assert all(c.feature == "symbols_per_word" for r in rules for c in r), rules  # what the table teaches
    stats = {d: plain_statistics(t) for d, t in rows.items()}
    left = {d: rows[d] for d, x in stats.items() if not x[5] and not any(all((read(x, c.feature) >= c.threshold) == c.above for c in r) for r in rules)}
    left = {d: left[d] for d, _, c in plain_components(list(left.items())) if d == c}
    bench = [(str(r.item_id), r.text) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    for d, n, hit, _ in brute_contamination(list(left.items()), bench):
        if hit and 20 * hit >= n:
            del left[d]
    table = spark.createDataFrame(list(left.items()), "doc_id long, text string")
    found = secrets.scanned(table, secrets.train(table)).collect()
    for r in found:
        t, out, up = left[r.doc_id], "", 0
        for a, b in sorted((x.start, x.end) for x in [*r._secrets.base, *r._secrets.added]):
            if a >= up:
                out += t[up:a] + secrets.MASK
            up = max(up, b)
        left[r.doc_id] = out + t[up:]
    check_packed(corpus_pipeline.run(spark, small).collect(), list(left.items()))


def test_stages_on_odd_tables(spark, small, tmp_path):
    """Nulls in any column, repeated rows, clashing extra columns, an empty table."""
    rnd = random.Random(1)
    say = lambda n: " ".join(f"w{rnd.randrange(10**5)}" for _ in range(n))
    text = say(60)
    rows = [(1, text, "en", None, 3), (1, text, "en", None, 3), (None, say(40), None, "s", None), (2, text, None, None, None), (3, None, "x", "y", 1), (4, "", "x", "y", 1), (5, say(30) + " token=abcdefgh12 x", "a", "b", 400), (None, None, None, None, None), (6, say(20000), "l", "m", 9)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, _kept int, _found string, contaminated int, n_words int, _ratio string, _base string, _keep_doc long, doc int, fp long, key int, bin int"
    extra = (1, None, 2, 3, "r", "b", 4, 5, 6, 7, 8)
    df = spark.createDataFrame([(*r, *extra) for r in rows], schema)
    for name, stage in corpus_pipeline.STAGES:
        for table in (df, df.limit(0)):
            out = stage(spark, table, small)
            got = out.collect()
            if name != "best-fit packing":
                assert out.columns == df.columns
            assert table is df or not got
            if table is df:
                ids = sorted((r.doc_id for r in got), key=str)
                if name == "quality rules":
                    assert ids == sorted([1, 1, None, 2, 5, 6], key=str)
                elif name == "SimHash near-dedup":
                    assert ids == sorted([1, None, 3, 5, 6], key=str)
                elif name == "benchmark decontamination":
                    assert len(got) == len(rows)
                elif name == "secret scans":
                    assert {r.doc_id: r.text.count("[SECRET]") for r in got if r.doc_id == 5} == {5: 1}
                    assert [r.n_chars for r in got if r.doc_id == 5] == [len(r.text) for r in got if r.doc_id == 5]
                    assert len(got) == len(rows)
                else:
                    assert sum(r.start == 0 for r in got) == len(rows)


def test_planted(spark, small):
    """Clean documents pass the filtering stages; contaminated ones and copies go."""
    rnd = random.Random(8)
    say = lambda n: " ".join("".join(rnd.choice("abcdefghij") for _ in range(rnd.randrange(2, 9))) for _ in range(n))
    passage = spark.read.parquet(f"{small}/benchmark.parquet").orderBy("item_id").first().text
    clean = [(k, say(80)) for k in range(30)]
    copies = [(100 + k, clean[k][1]) for k in range(5)]
    bad = [(200 + k, say(20) + " " + passage + " " + say(10)) for k in range(5)]
    df = spark.createDataFrame([(d, t, "en", "s", len(t)) for d, t in clean + copies + bad], "doc_id long, text string, lang string, source string, n_chars long")
    stages = [f for _, f in corpus_pipeline.STAGES]
    assert {r.doc_id for r in stages[0](spark, df, small).collect()} == {d for d, _ in clean + copies + bad}
    assert {r.doc_id for r in stages[1](spark, df, small).collect()} == {d for d, _ in clean + bad}
    assert {r.doc_id for r in stages[2](spark, df, small).collect()} == {d for d, _ in clean + copies}
    assert stages[3](spark, df, small).where(F.col("text").contains(secrets.MASK)).count() == 0
    assert decontam.words_of("A b-C") == [b"a", b"b", b"c"]
