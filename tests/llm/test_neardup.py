import random

import numpy as np
import xxhash

from sift.llm import neardup

SCHEMA = "doc_id long, text string, lang string, fp long"


def plain_fingerprint(text):
    words = [w for w in (text or "").encode().lower().split()]
    if not words:
        return 0
    sh = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hs = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def plain_components(rows):
    fp = [(d, plain_fingerprint(t)) for d, t in rows]
    root = {f: f for _, f in fp}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    fs = list(root)
    for i, a in enumerate(fs):
        for b in fs[:i]:
            if (a ^ b).bit_count() <= 3:
                root[find(a)] = find(b)
    least = {}
    for d, f in fp:
        if d is not None:
            least[find(f)] = min(least.get(find(f), d), d)
    return sorted(((d, f"{f:016x}", least.get(find(f))) for d, f in fp), key=str)


def found(spark, rows):
    df = spark.createDataFrame([(d, t, "x", 7) for d, t in rows], SCHEMA)
    return sorted(((r.doc, f"{r.fp & (2**64 - 1):016x}", r.component) for r in neardup.near_duplicates(df).collect()), key=str)


def test_edges(spark):
    assert found(spark, []) == []
    rnd = random.Random(3)
    base = [f"w{rnd.randrange(10**6)}" for _ in range(400)]
    rows = [(0, None), (1, ""), (2, " \t\n"), (3, "one"), (4, "One two"), (5, "one"), (None, "one"), (5, "one"), (6, "É é É")]
    for k in range(60):
        w = list(base)
        for _ in range(rnd.randrange(3)):
            w[rnd.randrange(400)] = "changed"
        rows.append((100 + k, " ".join(w)))
    rows.append((900, "long " * 50000))
    assert found(spark, rows) == plain_components(rows)


def test_whole_table(spark, small):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{small}/documents.parquet").collect()]
    got = sorted(map(tuple, neardup.op10_simhash_near_dedup(spark, small).collect()), key=str)
    assert got == plain_components(rows)


def test_dense_cell_links_are_a_forest():
    rnd = np.random.default_rng(1)
    base = np.uint64(0x0123456789ABCDEF)
    fp = np.unique(base ^ (np.uint64(1) << rnd.integers(0, 64, 500).astype(np.uint64)) ^ (np.uint64(1) << rnd.integers(0, 64, 500).astype(np.uint64)))
    a, b = neardup._pair_links(fp, 3)
    assert len(a) < len(fp) and all((int(x) ^ int(y)).bit_count() <= 3 for x, y in zip(a, b, strict=True))


def test_manhattan_bound():
    """The unary embedding's distance is the Manhattan distance of the counts, never above the number of differing bits."""
    rnd = np.random.default_rng(7)
    fp = rnd.integers(0, 1 << 63, 300, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    counts = np.array([[(int(f) >> (2 * k) & 3).bit_count() for k in range(32)] for f in fp])
    e = neardup.embedded(fp)
    for i in range(0, 300, 7):
        by = np.bitwise_count(e ^ e[i])
        assert (by == np.abs(counts - counts[i]).sum(axis=1)).all() and (by <= np.bitwise_count(fp ^ fp[i])).all()
    near = np.unique(np.concatenate([fp[:40] ^ (np.uint64(1) << rnd.integers(0, 64, 40).astype(np.uint64)) for _ in range(6)]))
    pairs, bound, links = neardup.pair_counts(near)
    assert pairs > 10 * bound and bound >= links > 0


def test_large_cells_lose_no_link():
    rnd = np.random.default_rng(2)
    base = rnd.integers(0, 1 << 63, 60, dtype=np.uint64)
    fp = np.unique(np.concatenate([base, *(base ^ (np.uint64(1) << rnd.integers(0, 64, 60).astype(np.uint64)) ^ (np.uint64(1) << rnd.integers(0, 64, 60).astype(np.uint64)) for _ in range(8))]))

    def groups(a, b):
        root = {int(f): int(f) for f in fp}

        def find(x):
            while root[x] != x:
                x = root[x]
            return x

        for x, y in zip(a.tolist(), b.tolist(), strict=True):
            assert (x ^ y).bit_count() <= 3
            root[find(x)] = find(y)
        return {f: min(g for g in root if find(g) == find(f)) for f in root}

    assert groups(*neardup._cell_links(fp, 3, large=50)) == groups(*neardup._pair_links(fp, 3))


def test_components_that_do_not_settle(spark, monkeypatch):
    import pytest

    monkeypatch.setattr(neardup, "ROUNDS", 1)
    links = spark.createDataFrame([(k, k + 1) for k in range(40)], "a long, b long")
    with pytest.raises(RuntimeError):
        neardup.components(links)
