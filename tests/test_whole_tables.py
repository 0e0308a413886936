"""Queries over rows of a table read all of them: counted against the given tables, not against the queries' SQL."""

import pytest


@pytest.fixture(scope="module")
def run(spark, tiny):
    import __spark_entry__

    queries = __spark_entry__.queries()
    return lambda key: queries[key](spark, tiny)


@pytest.mark.parametrize("name, id_col, keys", [("events", "event_id", "win_rank win_ntile udf_scalar sql_udf json_extract"), ("orders", "o_orderkey", "join_asof date_diff"), ("pages", "page_id", "str_url"), ("part", "p_partkey", "str_levenshtein")])
def test_a_row_for_every_row(spark, tiny, run, name, id_col, keys):
    want = sorted(r[0] for r in spark.read.parquet(f"{tiny}/{name}.parquet").select(id_col).collect())
    for key in keys.split():
        assert sorted(r[0] for r in run(key).select(id_col).collect()) == want, key


def test_sessions_words_and_ranges_cover_the_tables(spark, tiny, run):
    events = [r.event_id for r in spark.read.parquet(f"{tiny}/events.parquet").collect()]
    assert sum(r.n for r in run("st_session").collect()) == len(events)
    texts = [r.text for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()]
    assert sum(r.n for r in run("arr_explode").collect()) == sum(len(t.split(" ")) for t in texts)
    assert sorted(r.event_id for r in run("join_range").collect()) == sorted(e for e in events if e % 700 <= 50)


def test_workload_values_are_drawn_from_the_whole_table(spark, tiny):
    from sift import queries_measures
    from sift import workloads as W

    W.session(spark, tiny, "access_log")
    top = spark.read.parquet(f"{tiny}/events.parquet").count()
    for n in (20, 50):
        ids = sorted(int(name[1:]) for name, _ in queries_measures._queries(spark, "db_name", n, False))
        assert len(set(ids)) == n and ids[0] < top / 4 and ids[-1] > 3 * top / 4 and len({k % 97 for k in ids}) > 10
