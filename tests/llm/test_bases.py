import pytest

from sift.llm import queries
from tests.llm.helpers import plain, same_as_sql

KEYS = ["quality_base", "secrets_base", "lm_base"]
ODD = [
    None, "", " \n\t ", "a b c", "w " * 30, "one two three four five six seven eight " * 3, "x # $ | <y> & *%",
    "same line\nsame line\n\n \nsame line", "Password: hunter22 and TOKEN='abcdef' token=short api_key = \"a.b-c_d+e/f\"",
    "AKIA" + "Z9" * 9 + " AKIAshort AKIA" + "Q" * 16, "0123456789abcdef" * 3 + " deadbeef", "é😀 secret=ééabcdefgh secret=abcdefgh😀",
    "token=" + "0a" * 20, "\u017fecret=abcdefgh \u212aey", "apikey:abcdef passwd=abcdef",
]


@pytest.mark.parametrize("key", KEYS)
def test_whole_table(spark, small, key):
    assert same_as_sql(queries.QUERIES[key](spark, small), queries.ORACLES[key], small)


def test_odd_texts(spark, tmp_path):
    """Nulls, blanks, repeated rows and ids, letters beyond ASCII; then an empty table."""
    rows = [(k, t) for k, t in enumerate(ODD)] + [(3, "a b c"), (8, ODD[8])]
    for name, some in (("odd", rows), ("none", [])):
        docs = spark.createDataFrame(some, "doc_id long, text string")
        docs.coalesce(1).write.parquet(f"{tmp_path}/{name}/documents.parquet")
        spark.createDataFrame([], "doc_id long, quality int").coalesce(1).write.parquet(f"{tmp_path}/{name}/labels.parquet")
        for key in KEYS:
            df = queries.QUERIES[key](spark, f"{tmp_path}/{name}")
            names = sorted(df.columns)
            con = duck_documents(f"{tmp_path}/{name}")
            cur = con.execute(queries.ORACLES[key])
            have = [c[0] for c in cur.description]
            want = sorted((tuple(plain(r[have.index(n)]) for n in names) for r in cur.fetchall()), key=str)
            assert sorted((tuple(plain(r[n]) for n in names) for r in df.collect()), key=str) == want, key


def duck_documents(path):
    import duckdb

    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{path}/documents.parquet/*.parquet'")
    return con
