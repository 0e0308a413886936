"""Secret scans: fixed patterns, and runs of characters that a random source explains better than ordinary writing.

Two first-order character Markov models are trained from labelled samples, one of random strings (hexadecimal, base-64
and alphanumeric digests of counters), one of ordinary words and identifiers (words of a bounded sample of texts that
hold no secret by the patterns). A run of secret-like characters with letters and digits is reported where the
log-likelihood ratio of the two models passes a margin. All of it is DataFrame expressions; positions come from the
lengths of the matches and of what lies between them.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sift.llm.expr import fresh, let

#: Fixed patterns: kind, pattern, number of the group that has to be long, its least length.
BASE = (
    ("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 1, 6),
    ("access", r"AKIA[A-Z0-9]{16,}", 0, 20),
    ("hex", r"[0-9a-f]{24,}", 0, 24),
)
KIND = "random"
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
CANDIDATE = r"[A-Za-z0-9+/_=-]{16,}"
#: Texts whose words teach the model of ordinary writing at most, and random strings of each form.
SAMPLE_TEXTS = 2000
SAMPLE_RANDOM = 3000
#: Nats by which a run must be likelier under the random model, and nats a character.
MARGIN = 16.0
MARGIN_EACH = 0.75
MASK = "[SECRET]"


#: Spans in code points, with their text, and in bytes.
_SPAN = "array<struct<start:int,rank:int,end:int,value:string,a:int,b:int>>"
_BLOCK = 256


def _gathered(items: Column, state: Column, kind: str, step: Callable[[Column, Column], tuple[Column, Column]]) -> Column:
    """Goes through ``items`` with a state; ``step`` tells the next state and what to append (an array). All appended, as ``kind``.

    Blocks of items are gathered by themselves, so that appending copies little even where items are many.
    """
    empty = F.expr("array()").cast(kind)

    def one(s: Column, x: Column) -> Column:
        after, more = step(s["state"], x)
        return F.struct(after.alias("state"), F.concat(s["held"], more.cast(kind)).alias("held"))

    def block(s: Column, part: Column) -> Column:
        inner = F.aggregate(part, F.struct(s["state"].alias("state"), empty.alias("held")), one)
        return let(inner, lambda r: F.struct(r["state"].alias("state"), F.concat(s["held"], r["held"]).alias("held")))

    blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(items) - 1) / _BLOCK).cast("int")), lambda i: F.slice(items, i * _BLOCK + 1, F.lit(_BLOCK)))
    return F.when(F.size(items) == 0, empty).otherwise(F.aggregate(blocks, F.struct(state.alias("state"), empty.alias("held")), block, lambda s: s["held"]))


def _spans(text: Column, pattern: str, rank: int, group: int, least: int) -> Column:
    """Leftmost non-overlapping matches as ``_SPAN``, those with too short a group dropped."""
    whole, inner = F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.regexp_extract_all(text, F.lit(pattern), F.lit(group))

    def placed(m: Column) -> Column:
        joined = F.filter(F.arrays_zip(m["whole"].alias("w"), m["inner"].alias("g"), m["between"].alias("b")), lambda x: x["w"].isNotNull())

        def step(s: Column, x: Column) -> tuple[Column, Column]:
            start, a = s["at"] + F.length(x["b"]), s["byte"] + F.octet_length(x["b"])
            end, b = start + F.length(x["w"]), a + F.octet_length(x["w"])
            one = F.array(F.struct(start.alias("start"), F.lit(rank).alias("rank"), end.alias("end"), x["w"].alias("value"), a.alias("a"), b.alias("b"))).cast(_SPAN)
            return F.struct(end.alias("at"), b.alias("byte")), F.when(F.length(x["g"]) >= least, one).otherwise(F.expr("array()").cast(_SPAN))

        return let(joined, lambda j: _gathered(j, F.struct(F.lit(0).alias("at"), F.lit(0).alias("byte")), _SPAN, step))

    parts = F.struct(whole.alias("whole"), inner.alias("inner"), F.split(text, pattern, -1).alias("between"))
    return F.when(text.rlike(pattern), let(parts, placed)).otherwise(F.expr("array()").cast(_SPAN))


def _merged(spans: Column, size: Column) -> Column:
    """Maximal stretches (a, b) of overlapping ``spans`` (sorted), in bytes; ``size`` is the text's."""
    kind = "array<struct<a:int,b:int>>"
    items = F.concat(F.transform(spans, lambda x: F.struct(x["a"].alias("a"), x["b"].alias("b"))), F.array(F.struct(size.alias("a"), size.alias("b"))))

    def step(open_: Column, x: Column) -> tuple[Column, Column]:
        inside = x["a"] < open_["b"]
        after = F.struct(F.when(inside, open_["a"]).otherwise(x["a"]).alias("a"), F.when(inside, F.greatest(open_["b"], x["b"])).otherwise(x["b"]).alias("b"))
        return after, F.when(inside | (open_["b"] < 0), F.expr("array()").cast(kind)).otherwise(F.array(open_))

    return let(items, lambda i: _gathered(i, F.struct(F.lit(-1).alias("a"), F.lit(-1).alias("b")), kind, step))


def _replaced(text: Column, spans: Column, by: Callable[[Column], Column]) -> Column:
    """``text`` with every maximal stretch of overlapping ``spans`` (sorted) replaced by ``by`` of its size in bytes."""

    def spelt(m: Column, raw: Column) -> Column:
        def piece(x: Column, i: Column) -> Column:
            up = F.when(i == 0, F.lit(0)).otherwise(F.get(m, i - 1)["b"])
            return F.concat(F.decode(F.substring(raw, up + 1, x["a"] - up), "UTF-8"), by(x["b"] - x["a"]))

        last = F.element_at(m, -1)["b"]
        return F.concat(F.array_join(F.transform(m, piece), ""), F.decode(F.substring(raw, last + 1, F.octet_length(raw) - last), "UTF-8"))

    replaced = let(F.encode(text, "UTF-8"), lambda raw: let(_merged(spans, F.octet_length(raw)), lambda m: spelt(m, raw)))
    return F.when(F.size(spans) == 0, text).otherwise(replaced)


def base_spans(text: Column) -> Column:
    """The fixed patterns' spans, by start, then kind."""
    return F.array_sort(F.concat(*(_spans(text, p, k, g, n) for k, (_, p, g, n) in enumerate(BASE))))


def _transitions(strings: DataFrame) -> DataFrame:
    """(t, n): counts of adjacent characters in the column ``s``."""
    chars = F.split("s", "")
    pairs = strings.select(chars.alias("c")).select(F.explode(F.transform("c", lambda x, i: F.concat(x, F.coalesce(F.get("c", i + 1), F.lit(""))))).alias("t"))
    return pairs.where("length(t) = 2").groupBy("t").agg(F.count("*").alias("n"))


def random_strings(spark: SparkSession, each: int = SAMPLE_RANDOM) -> DataFrame:
    """Labelled sample of random strings, the same each time."""
    d = F.sha2(F.col("id").cast("string"), 256)
    forms = [d.substr(1, 40), F.base64(F.unhex(d)).substr(1, 40), F.regexp_replace(F.base64(F.unhex(F.sha2(F.concat(F.lit("a"), F.col("id").cast("string")), 256))), "[+/=]", ""), F.upper(F.regexp_replace(F.base64(F.unhex(F.sha2(F.concat(F.lit("b"), F.col("id").cast("string")), 256))), "[+/=]", ""))]
    return spark.range(each).select(F.explode(F.array(*forms)).alias("s"))


def ordinary_strings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE_TEXTS) -> DataFrame:
    """Labelled sample of ordinary strings: words of at most ``sample`` texts (by a hash of the id) in which no pattern matches."""
    chosen = docs.select(F.col(id_col).alias("_id")).where("_id is not null").distinct().orderBy(F.xxhash64("_id"), "_id").limit(sample)
    text = F.coalesce(F.col("_text"), F.lit(""))
    clean = reduce(lambda a, b: a & b, (~text.rlike(p) for _, p, _, _ in BASE))
    read = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text")).join(F.broadcast(chosen), "_id")
    return read.where(clean).select(F.explode(F.regexp_extract_all(text, F.lit(r"[A-Za-z0-9+/_=-]{3,}"), F.lit(0))).alias("s"))


def train(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> list[float]:
    """Log-likelihood ratios of all transitions, row by row over the alphabet; add-one smoothed in both models."""
    rows = [{r.t: r.n for r in _transitions(x).collect()} for x in (random_strings(docs.sparkSession), ordinary_strings(docs, id_col, text_col))]  # a row for each pair of characters at most
    ratio = []
    for a in ALPHABET:
        per = [[c.get(a + b, 0) + 1 for b in ALPHABET] for c in rows]
        total = [sum(x) for x in per]
        ratio += [math.log(r / total[0]) - math.log(o / total[1]) for r, o in zip(*per, strict=True)]
    return ratio


def random_spans(text: Column, ratio: Column) -> Column:
    """Spans of candidate runs whose log-likelihood ratio, by the table ``ratio``, passes the margin."""
    width = len(ALPHABET)

    def likely(x: Column) -> Column:
        codes = F.transform(F.split(x["value"], ""), lambda c: F.instr(F.lit(ALPHABET), c) - 1)
        total = let(codes, lambda k: F.aggregate(F.transform(k, lambda c, i: F.when(F.get(k, i + 1).isNull(), F.lit(0.0)).otherwise(F.get(ratio, c * width + F.get(k, i + 1)))), F.lit(0.0), lambda a, v: a + v))
        n = F.length(x["value"]) - 1
        return x["value"].rlike("[0-9]") & x["value"].rlike("[A-Za-z]") & (total >= F.greatest(F.lit(MARGIN), MARGIN_EACH * n))

    return F.filter(_spans(text, CANDIDATE, len(BASE), 0, 0), likely)


def scanned(docs: DataFrame, ratio: list[float], text_col: str = "text", name: str = "_secrets") -> DataFrame:
    """``docs`` with a struct column of base and added (arrays of start, rank, end, value, a, b), in code points and in bytes.

    rank 0 assign, 1 access, 2 hex, 3 random; an added span overlaps no base span, for runs are looked for in what base
    spans leave. A null text is empty. Other columns are carried along untouched; none may be called ``name``.
    """
    text = F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit(""))
    held, base = fresh(docs, "_ratio"), fresh(docs, "_base")
    table = F.split(F.lit(",".join(repr(x) for x in ratio)), ",").cast("array<double>")  # one literal, folded once
    marked = docs.withColumn(held, table).withColumn(base, base_spans(text))
    # Base spans are of ASCII characters only, so blanks in their place keep all positions.
    left = _replaced(text, F.col(base), lambda n: F.repeat(F.lit(" "), n))
    added = let(left, lambda t: random_spans(t, F.col(held)))
    return marked.withColumn(name, F.struct(F.col(base).alias("base"), added.alias("added"))).drop(base, held)


def spelled(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    kinds = F.array(*(F.lit(k) for k in (*(b[0] for b in BASE), KIND)))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(kinds, x["rank"]), x["start"].cast("string"), x["end"].cast("string"))), ",")


def masked(text: Column, spans: Column, mask: str = MASK) -> Column:
    """``text`` with every maximal stretch of overlapping spans replaced by ``mask``."""
    return let(F.array_sort(spans), lambda x: _replaced(text, x, lambda n: F.lit(mask)))


def op6_secret_scans(spark, sf_dir: str) -> DataFrame:
    """Counts and spans of secrets in every document."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = scanned(docs, train(docs))
    base, rank = F.col("_secrets.base"), lambda k: F.size(F.filter("_secrets.base", lambda x: x["rank"] == k)).cast("long")
    return found.select(
        "doc_id",
        *(rank(k).alias(f"n_{b[0]}") for k, b in enumerate(BASE)),
        F.sha2(spelled(base), 256).alias("base_sha256"),
        spelled(F.array_sort(F.concat("_secrets.base", "_secrets.added"))).alias("spans"),
    )
