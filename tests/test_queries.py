"""A cut through the registered queries against DuckDB, at the smallest scale; tests/compare.py runs all of them."""

import pytest

from tests.oracle import duck, plain

KEYS = """core_range core_and_or_not core_in_long core_join_two_lakes core_self_join core_not_in_null minmax_content minmax_footer minmax_decimal gaps_content gaps_choose_range
gaps_choose_exact boxes_content boxes_multi geo_contains_notched geo_distance geo_not_contains bloom_in list_not_like prefix_long suffix_like head_tail_underscore hybrid_like hybrid_choice hybrid_threshold
template_udf template_json ring_euclid ring_levenshtein ring_centroid ring_user_metric geo_shape_boxes struct_field_skip binary_template encrypted_with_key encrypted_without_key encrypted_wrong_key partition_by_summary refresh_after stream_index_equals_batch
store_document store_table format_text format_csv ind_prefix ind_agent ind_geomean ind_identity select_dp select_greedy cost_model join_prune motivating_query join_asof join_range st_session st_stateful tpch_q3 udtf_explain""".split()


@pytest.fixture(scope="module")
def entry():
    import __spark_entry__

    return __spark_entry__


@pytest.mark.parametrize("key", KEYS)
def test_same_as_sql(spark, tiny, entry, key):
    df = entry.queries()[key](spark, tiny)
    names = sorted(df.columns)
    got = sorted((tuple(plain(r[n]) for n in names) for r in df.collect()), key=str)
    cur = duck(tiny).execute(entry.oracle_sql()[key])
    have = [c[0] for c in cur.description]
    assert sorted(have) == names
    assert got == sorted((tuple(plain(r[have.index(n)]) for n in names) for r in cur.fetchall()), key=str)


def test_entry(spark, entry):
    assert entry.entry(spark).columns == ["max_temp"]


def test_oracles_have_queries(entry):
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_rest_stands_without_the_llm_folders(tmp_path):
    """The driver deletes the optional folders and corpus_pipeline.py: the entry point must still import."""
    import os
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(os.path.join(root, "sift"), tmp_path / "sift", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(os.path.join(root, "__spark_entry__.py"), tmp_path)
    out = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; q = e.queries(); print(len(q), 'pipeline' in q, any(k.startswith('op1_') for k in q))"], cwd=tmp_path, capture_output=True, text=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})
    assert out.stdout.split()[1:] == ["False", "False"], out.stderr
