"""Every registered query against its SQL: python tests/compare.py SF_DIR [KEY...]"""

import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

from tests.oracle import duck, plain  # noqa: E402


def rows_equal(a, b):
    return sorted(a, key=str) == sorted(b, key=str)


def main(sf_dir, keys):
    from pyspark.sql import SparkSession

    import __spark_entry__ as e

    spark = SparkSession.builder.master("local[6]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    queries, oracles = e.queries(), e.oracle_sql()
    con, bad = duck(sf_dir), 0
    for key in keys or [k for k in queries if not k.startswith(("op", "pipeline"))]:
        began = time.time()
        try:
            df = queries[key](spark, sf_dir)
            names = sorted(df.columns)
            got = [tuple(plain(r[n]) for n in names) for r in df.collect()]
            word = "rows-only"
            if key in oracles:
                cur = con.execute(oracles[key])
                have = [c[0] for c in cur.description]
                want = [tuple(plain(r[have.index(n)]) for n in names) for r in cur.fetchall()] if sorted(have) == names else f"columns {have}"
                if isinstance(want, str):
                    word = f"BAD {want} vs {names}"
                elif rows_equal(got, want):
                    word = "same"
                else:
                    diff = [x for x in sorted(got, key=str) if x not in set(want)][:2], [x for x in sorted(want, key=str) if x not in set(got)][:2]
                    word = f"BAD {len(got)} vs {len(want)} rows: {diff}"
        except Exception as x:
            word, got = f"BAD {type(x).__name__}: {str(x)[:300]}".replace("\n", " "), []
        bad += word.startswith("BAD")
        print(f"{key}: {word} ({len(got)} rows, {time.time() - began:.1f} s)", flush=True)
    print("failures:", bad)


if __name__ == "__main__":
    main(sys.argv[1], sys.argv[2:])
