"""URL filters: fixed rules first, else an empirical-Bayes reputation of the host.

Labelled page outcomes (bad or not) are counted by host, registered domain and suffix. Each level's prior strength is
estimated from how much the rates of its members differ beyond chance; a member's beta posterior takes its parent's
posterior mean as prior mean, so a host without labels inherits its domain's reputation, and that of its suffix. A host
is blocked where the lower bound of its bad rate passes a limit.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sift.runtime import materialise

#: Fixed values: (host, path, verdict) of the rules.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
#: Suffixes of two labels, under which names are registered.
SUFFIXES = ("ac.uk", "co.in", "co.jp", "co.nz", "co.uk", "co.za", "com.au", "com.br", "com.cn", "com.mx", "org.au", "org.uk")
#: Standard deviations below the mean at which the bound lies, and the bad rate it must pass.
Z = 1.645
LIMIT = 0.3
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    """What follows the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; empty if there is none."""
    u = F.coalesce(url, F.lit(""))
    return F.translate(F.regexp_extract(u, r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    """What follows the host up to ``?``, ``#`` or the end; empty if there is no ``://``."""
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest fitting rule, spelled host and path, and its verdict; null where none fits."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for h, p, v in sorted(rules, key=lambda r: len(r[0] + r[1])):  # the longest is tested first
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        name, verdict = F.when(fits, h + p).otherwise(name), F.when(fits, v).otherwise(verdict)
    return name, verdict


def suffix_of(host: Column) -> Column:
    """The last label, or the last two where these are a known suffix; the port is left out."""
    name = F.regexp_replace(host, r":[0-9]*$", "")
    two = F.regexp_extract(name, r"([^.]+\.[^.]+)$", 1)
    return F.when(two.isin(*SUFFIXES), two).otherwise(F.regexp_extract(name, r"([^.]*)$", 1))


def domain_of(host: Column, suffix: Column) -> Column:
    """The suffix and the label before it; the suffix itself if nothing is before it."""
    name = F.regexp_replace(host, r":[0-9]*$", "")
    rest = F.substring(name, F.lit(1), F.greatest(F.lit(0), F.length(name) - F.length(suffix) - 1))
    before = F.regexp_extract(rest, r"([^.]*)$", 1)
    return F.when(before == "", suffix).otherwise(F.concat(before, F.lit("."), suffix))


def _strength(w: float, k1: float, w2: float, kk: float, m: float) -> float:
    """Prior strength of a level by moments, from 1 to 1000; of its members' n and k: sums of n, k, n², k²/n, and their number."""
    p = k1 / w if w else 0.0
    scatter = kk - k1 * p - p * (1 - p) * (m - 1)
    scale = p * (1 - p) * (w - (w2 / w if w else 0.0) - (m - 1))
    rho = scatter / scale if scale > 0 else 0.0
    return 1 / min(max(rho, 1 / 1001), 0.5) - 1


def reputations(hosts: DataFrame, outcomes: DataFrame) -> DataFrame:
    """(host, n, k, mean, bound) for each row of ``hosts`` (column host), from ``outcomes`` (host, bad)."""
    parts = lambda df: df.withColumn("suffix", suffix_of(F.col("host"))).withColumn("domain", domain_of(F.col("host"), F.col("suffix")))
    by_host = materialise(parts(outcomes.groupBy("host").agg(F.count("*").alias("n"), F.sum(F.col("bad").cast("long")).alias("k"))), "hosts")
    by_domain = by_host.groupBy("domain", "suffix").agg(F.sum("n").alias("n"), F.sum("k").alias("k"))
    by_suffix = by_domain.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("k").alias("k"))
    levels = (("suffix", by_suffix), ("domain", by_domain), ("host", by_host))
    sums = [df.agg(F.lit(name).alias("level"), *(F.coalesce(F.sum(x), F.lit(0)).cast("double").alias(a) for x, a in (("n", "w"), ("k", "k1"), (F.col("n") * F.col("n"), "w2"), (F.col("k") * F.col("k") / F.col("n"), "kk"), (F.lit(1), "m")))) for name, df in levels]
    told = {r.level: r for r in sums[0].unionByName(sums[1]).unionByName(sums[2]).collect()}  # a row for each of the three levels
    out = parts(hosts)
    for name, level in levels:
        out = out.join(level.select(name, F.col("n").alias(f"_n_{name}"), F.col("k").alias(f"_k_{name}")), name, "left")
    held = {c: [F.lit(told["host"][total]), *(F.coalesce(f"_{c}_{name}", F.lit(0)) for name, _ in levels), F.lit(0)] for c, total in (("n", "w"), ("k", "k1"))}
    # What a member adds is taken out of its parent, so that no outcome counts twice.
    n, k = ([x[i] - x[i + 1] for i in range(4)] for x in (held["n"], held["k"]))
    out = out.withColumn("_m0", (k[0] + 1) / (n[0] + 10))
    for i, (name, _) in enumerate(levels, 1):
        r = told[name]
        s = F.lit(_strength(r.w, r.k1, r.w2, r.kk, r.m))
        out = out.withColumn(f"_m{i}", (s * F.col(f"_m{i - 1}") + k[i]) / (s + n[i]))
    deviation = F.sqrt(F.col("_m3") * (1 - F.col("_m3")) / (s + n[3] + 1))
    return out.select("host", n[3].alias("n"), k[3].alias("k"), F.col("_m3").alias("mean"), (F.col("_m3") - Z * deviation).alias("bound"))


def url_verdicts(pages: DataFrame, outcomes: DataFrame, id_col: str = "page_id", url_col: str = "url", rules=RULES, limit: float = LIMIT) -> DataFrame:
    """(id, host, path, rule, verdict, n_labelled) for every row of ``pages``.

    ``outcomes`` has the page's id in column id and its outcome in column bad (null: no outcome); several outcomes of a
    page all count. A url that is null or has no ``://`` has an empty host and path and is judged by the reputation
    of the empty host. Without any outcome everything that no rule blocks is allowed. Repeated rows stay.
    """
    rows = pages.select(F.col(id_col).alias("id"), host_of(F.col(url_col).cast("string")).alias("host"), path_of(F.col(url_col).cast("string")).alias("path"))
    seen = rows.select("id", "host").join(outcomes.where("bad is not null").select("id", "bad"), "id").select("host", "bad")
    # Stored, so that the join below has two plain exchanges, whose skewed partitions (a host with a third of all pages) can be split.
    known = materialise(reputations(rows.select("host").distinct(), seen), "reputations")
    judged = rows.join(known, "host", "left")
    rule, verdict = rule_of(F.col("host"), F.col("path"), rules)
    own = F.when(F.col("bound") > limit, "block").otherwise("allow")
    return judged.select("id", "host", "path", rule.alias("rule"), F.coalesce(verdict, own).alias("verdict"), F.col("n").alias("n_labelled"))


def op2_url_filters(spark, sf_dir: str) -> DataFrame:
    """Every page's url judged; a page's outcome is the quality label under its id (0: bad)."""
    pages, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("pages", "labels"))
    outcomes = labels.select(F.col("doc_id").alias("id"), (F.col("quality") == 0).alias("bad"))
    return url_verdicts(pages, outcomes).withColumnRenamed("id", "page_id")


def _oracle() -> str:
    two = ", ".join(f"'{s}'" for s in SUFFIXES)

    def level(name: str, source: str) -> str:
        p = "(k1 / nullif(w, 0))"
        scale = f"({p} * (1 - {p}) * (w - w2 / nullif(w, 0) - (m - 1)))"
        scatter = f"(kk - k1 * {p} - {p} * (1 - {p}) * (m - 1))"
        return f"""s_{name} AS (SELECT 1 / least(greatest(CASE WHEN {scale} > 0 THEN {scatter} / {scale} ELSE 0.0 END, 1e0 / 1001), 0.5) - 1 AS s
  FROM (SELECT CAST(coalesce(sum(n), 0) AS DOUBLE) AS w, CAST(coalesce(sum(k), 0) AS DOUBLE) AS k1, CAST(coalesce(sum(n * n), 0) AS DOUBLE) AS w2, CAST(coalesce(sum(CAST(k * k AS DOUBLE) / n), 0) AS DOUBLE) AS kk, CAST(count(*) AS DOUBLE) AS m FROM {source}))"""

    cases = " ".join(f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN '{{}}'".format(f"{h}{p}") for h, p, _ in sorted(RULES, key=lambda r: -len(r[0] + r[1])))
    verdicts = " ".join(f"WHEN '{h}{p}' THEN '{v}'" for h, p, v in RULES)
    return f"""
WITH rows_ AS (SELECT page_id, translate(regexp_extract(coalesce(url, ''), '^.*?://([^/?#]*)', 1, 's'), '{UPPER}', '{LOWER}') AS host,
                      regexp_extract(coalesce(url, ''), '^.*?://[^/?#]*([^?#]*)', 1, 's') AS path FROM pages),
all_hosts AS (SELECT DISTINCT host, regexp_replace(host, ':[0-9]*$', '') AS name FROM rows_),
with_suffix AS (SELECT host, name, CASE WHEN regexp_extract(name, '([^.]+\\.[^.]+)$', 1) IN ({two}) THEN regexp_extract(name, '([^.]+\\.[^.]+)$', 1) ELSE regexp_extract(name, '([^.]*)$', 1) END AS suffix FROM all_hosts),
with_before AS (SELECT host, suffix, regexp_extract(substring(name, 1, greatest(0, length(name) - length(suffix) - 1)), '([^.]*)$', 1) AS before FROM with_suffix),
hosts AS (SELECT host, suffix, CASE WHEN before = '' THEN suffix ELSE before || '.' || suffix END AS domain FROM with_before),
by_host AS (SELECT h.host, h.domain, h.suffix, count(*) AS n, sum(CASE WHEN l.quality = 0 THEN 1 ELSE 0 END) AS k
            FROM rows_ r JOIN labels l ON l.doc_id = r.page_id JOIN hosts h ON h.host = r.host WHERE l.quality IS NOT NULL GROUP BY 1, 2, 3),
by_domain AS (SELECT domain, suffix, sum(n) AS n, sum(k) AS k FROM by_host GROUP BY 1, 2),
by_suffix AS (SELECT suffix, sum(n) AS n, sum(k) AS k FROM by_domain GROUP BY 1),
root AS (SELECT coalesce(sum(n), 0) AS n, coalesce(sum(k), 0) AS k FROM by_suffix),
{level('suffix', 'by_suffix')},
{level('domain', 'by_domain')},
{level('host', 'by_host')},
c AS (SELECT h.host, CAST(root.n AS DOUBLE) AS n0, CAST(root.k AS DOUBLE) AS k0, coalesce(x.n, 0) AS n1, coalesce(x.k, 0) AS k1, coalesce(y.n, 0) AS n2, coalesce(y.k, 0) AS k2, coalesce(z.n, 0) AS n3, coalesce(z.k, 0) AS k3, s1.s AS s1, s2.s AS s2, s3.s AS s3
      FROM hosts h CROSS JOIN root CROSS JOIN s_suffix s1 CROSS JOIN s_domain s2 CROSS JOIN s_host s3
      LEFT JOIN by_suffix x ON x.suffix = h.suffix LEFT JOIN by_domain y ON y.domain = h.domain LEFT JOIN by_host z ON z.host = h.host),
m1 AS (SELECT *, (s1 * ((k0 - k1 + 1) / (n0 - n1 + 10)) + (k1 - k2)) / (s1 + (n1 - n2)) AS m1 FROM c),
m2 AS (SELECT *, (s2 * m1 + (k2 - k3)) / (s2 + (n2 - n3)) AS m2 FROM m1),
m3 AS (SELECT *, (s3 * m2 + k3) / (s3 + n3) AS m FROM m2),
rep AS (SELECT host, n3 AS n, m - {Z} * sqrt(m * (1 - m) / (s3 + n3 + 1)) AS bound FROM m3),
ruled AS (SELECT *, CASE {cases} ELSE NULL END AS rule FROM rows_)
SELECT r.page_id, r.host, r.path, r.rule, coalesce(CASE r.rule {verdicts} ELSE NULL END, CASE WHEN rep.bound > {LIMIT} THEN 'block' ELSE 'allow' END) AS verdict, CAST(rep.n AS BIGINT) AS n_labelled
FROM ruled r JOIN rep ON rep.host = r.host
"""


ORACLE = _oracle()
