import re

from sift.llm import reputation

from .helpers import same_as_sql


def split_url(u):
    if not u or "://" not in u:
        return "", ""
    rest = u.split("://", 1)[1]
    host = re.split(r"[/?#]", rest, maxsplit=1)[0]
    return re.sub("[A-Z]", lambda m: m[0].lower(), host), re.split(r"[?#]", rest[len(host) :], maxsplit=1)[0]


def plain_rule(host, path):
    fits = [(len(h + p), h + p, v) for h, p, v in reputation.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return max(fits)[1:] if fits else (None, None)


def test_same_as_sql(spark, small):
    same_as_sql(reputation.op2_url_filters(spark, small), reputation.ORACLE, small)


def test_edges(spark):
    urls = [None, "", "no scheme", "://", "http://", "HTTP://WWW.Example.NET/en/x?y", "http://example.net", "http://a.example.net/en/", "http://notexample.net/en/", "http://x.com://y/z", "http://example.com/de/a#b", "http://b.example.org/fr/x", "http://net/", "http://net?x=/", "http://É.Org/fr/1", "http://h.co.uk:80/p\nq?r", "http://h.co.uk:80/p\nq?r", "x" * 100000]
    pages = spark.createDataFrame([(k, u, 3, "bad") for k, u in enumerate(urls)] + [(None, "http://z.org/", 1, "")], "page_id long, url string, n int, rule string")
    outcomes = spark.createDataFrame([(3, True), (3, None), (15, False), (None, True)], "id long, bad boolean")
    got = {r.id: r for r in reputation.url_verdicts(pages, outcomes).collect()}
    assert len(got) == len(urls) + 1
    for k, u in enumerate(urls):
        host, path = split_url(u)
        rule, verdict = plain_rule(host, path)
        assert (got[k].host, got[k].path, got[k].rule) == (host, path, rule), u
        if rule:
            assert got[k].verdict == verdict
    assert reputation.url_verdicts(pages.limit(0), outcomes).collect() == []
    assert {r.verdict for r in reputation.url_verdicts(pages, outcomes.limit(0)).collect() if r.rule is None} == {"allow"}


def test_shrinkage(spark):
    """A host seen often and always bad is blocked, as is its unseen sister; one bad page alone does not block a host."""
    rows, marks, i = [], [], 0
    for h, n, bad in [("a.evil.com", 60, 60), ("b.evil.com", 50, 49), ("fine.com", 80, 2), ("other.org", 1, 1), ("good.org", 90, 0), ("nice.org", 70, 1), ("ok.com", 60, 3)]:
        for k in range(n):
            rows.append((i, f"http://{h}/{k}"))
            marks.append((i, k < bad))
            i += 1
    rows.append((i, "http://new.evil.com/"))
    got = {r.host: r.verdict for r in reputation.url_verdicts(spark.createDataFrame(rows, "page_id long, url string"), spark.createDataFrame(marks, "id long, bad boolean")).collect()}
    assert got == {"a.evil.com": "block", "b.evil.com": "block", "new.evil.com": "block", "fine.com": "allow", "other.org": "allow", "good.org": "allow", "nice.org": "allow", "ok.com": "allow"}
