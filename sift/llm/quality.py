"""Quality rules: a learned decision list over text statistics, in DataFrame expressions only.

The statistics of a text are computed row by row inside one projection. Sequential covering then learns, from labelled
texts, conjunctions of thresholds that single out rejected texts: a rule is grown condition by condition on two thirds
of the sample by information gain and pruned on the rest; the texts that it covers leave the sample and the next rule
is learnt. The list is emitted as one ordered conditional expression.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sift.llm.expr import fresh, let

SPACE = r"[\x20\x09-\x0D]+"
WINDOW = 8
MIN_WORDS = 20
MAX_REPEAT_PERCENT = 30
#: Labelled texts that the list is learnt from at most; a fixed hash of the id picks them.
SAMPLE = 4000
MAX_RULES = 8
MAX_CONDITIONS = 3
THRESHOLDS = 24
#: What a rule must reach on the growing and on the pruning part of the sample.
PRECISION = 0.97
COVERS = 12


def words_of(text: Column) -> Column:
    """Array of the words between ASCII white space; empty for null."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACE), lambda w: w != "")


def _n_repeated(words: Column) -> Column:
    """Words inside windows of eight that occur at least twice in the text, the first occurrence included."""
    n = F.size(words)
    at = F.sequence(F.lit(1), n - (WINDOW - 1))

    def covered(windows: Column) -> Column:
        # Sorted (window, place) pairs put equal windows side by side.
        kept = F.filter(F.transform(windows, lambda x, i: F.when((F.get(windows, i - 1)["w"] == x["w"]) | (F.get(windows, i + 1)["w"] == x["w"]), x["i"])), lambda i: i.isNotNull())
        return let(F.array_sort(kept), lambda p: F.aggregate(p, F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).alias("up")), lambda s, i: F.struct((s["n"] + i + WINDOW - F.greatest(i, s["up"])).cast("long").alias("n"), (i + WINDOW).alias("up")), lambda s: s["n"]))

    spelled = F.transform(at, lambda i: F.struct(F.array_join(F.slice(words, i, WINDOW), " ").alias("w"), i.alias("i")))
    slow = let(F.array_sort(spelled), covered)
    # Most texts repeat nothing: the windows' hashes are then all different, and no window need be spelled out.
    hashes = F.transform(at, lambda i: F.xxhash64(F.slice(words, i, WINDOW)))
    return F.when(n <= WINDOW, F.lit(0).cast("long")).when(let(hashes, lambda h: F.size(F.array_distinct(h)) == F.size(h)), F.lit(0).cast("long")).otherwise(slow)


def statistics(text: Column) -> Column:
    """Struct of n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (long) of a text; all zero for null."""
    filled = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(filled, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))

    def of(words: Column) -> Column:
        return F.struct(
            F.size(words).cast("long").alias("n_words"),
            F.length(F.array_join(words, "")).cast("long").alias("word_chars"),
            F.length(F.regexp_replace(filled, r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
            let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
            _n_repeated(words).alias("n_repeat_words"),
        )

    return let(words_of(text), of)


def base_failed(s: Column) -> Column:
    """Too short, or more than 30 in a hundred words inside repeated windows."""
    return (s["n_words"] < MIN_WORDS) | (100 * s["n_repeat_words"] > MAX_REPEAT_PERCENT * s["n_words"])


#: What rules set thresholds on.
FEATURES: dict[str, Callable[[Column], Column]] = {
    "symbols_per_word": lambda s: s["n_symbols"] / F.greatest(s["n_words"], F.lit(1)),
    "dup_lines_per_100_words": lambda s: 100 * s["n_dup_lines"] / F.greatest(s["n_words"], F.lit(1)),
    "repeat_share": lambda s: s["n_repeat_words"] / F.greatest(s["n_words"], F.lit(1)),
    "chars_per_word": lambda s: s["word_chars"] / F.greatest(s["n_words"], F.lit(1)),
    "n_words": lambda s: s["n_words"].cast("double"),
    "shouting": lambda s: s["shouting"],
    "same_as_next": lambda s: s["same_as_next"],
}


def features(text: Column, s: Column) -> Column:
    """Struct of the features; two are read off the text: upper-case share of letters, and of words equal to the next one."""
    filled = F.coalesce(text, F.lit(""))
    letters = F.greatest(F.length(F.regexp_replace(filled, r"[^\p{L}]+", "")), F.lit(1))
    pairs = let(words_of(text), lambda w: F.aggregate(w, F.struct(F.lit("").alias("last"), F.lit(0).alias("n")), lambda a, x: F.struct(x.alias("last"), (a["n"] + F.when(F.lower(a["last"]) == F.lower(x), 1).otherwise(0)).alias("n")), lambda a: a["n"]))
    own = {"shouting": F.length(F.regexp_replace(filled, r"[^\p{Lu}]+", "")) / letters, "same_as_next": pairs / F.greatest(s["n_words"], F.lit(1))}
    return F.struct(*((own[k] if k in own else f(s)).cast("double").alias(k) for k, f in FEATURES.items()))


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    threshold: float

    def holds(self, row: dict) -> bool:
        return row[self.feature] >= self.threshold if self.above else row[self.feature] < self.threshold

    def column(self, f: Column) -> Column:
        return f[self.feature] >= self.threshold if self.above else f[self.feature] < self.threshold


Rule = tuple[Condition, ...]


def _gain(p0: int, n0: int, p: int, n: int) -> float:
    """Covered positives times the gain in the information of knowing a positive."""
    return p * (math.log2(p / (p + n)) - math.log2(p0 / (p0 + n0))) if p else -1.0


def _counts(rows: list[tuple[dict, bool]], rule: Rule) -> tuple[int, int]:
    p = sum(bad for x, bad in rows if all(c.holds(x) for c in rule))
    return p, sum(all(c.holds(x) for c in rule) for x, _ in rows) - p


def _grow(rows: list[tuple[dict, bool]]) -> Rule:
    rule: Rule = ()
    while len(rule) < MAX_CONDITIONS:
        p0 = sum(bad for _, bad in rows)
        n0 = len(rows) - p0
        if not p0 or not n0:
            break
        best, best_gain = None, 1e-9
        for f in FEATURES:
            values = sorted({x[f] for x, _ in rows})
            step = max(1, len(values) // THRESHOLDS)
            for v in sorted({*values[1::step], *values[-3:]}):
                for c in (Condition(f, True, v), Condition(f, False, v)):
                    p = n = 0
                    for x, bad in rows:
                        if c.holds(x):
                            p, n = p + bad, n + (not bad)
                    if (g := _gain(p0, n0, p, n)) > best_gain:
                        best, best_gain = c, g
        if best is None:
            break
        rule = (*rule, best)
        rows = [(x, bad) for x, bad in rows if best.holds(x)]
    return rule


def _prune(rule: Rule, rows: list[tuple[dict, bool]]) -> Rule:
    """Last conditions fall while the rule's worth on the pruning part doesn't."""

    def worth(r: Rule) -> float:
        p, n = _counts(rows, r)
        return (p - n) / (p + n) if p + n else -1.0

    while len(rule) > 1 and worth(rule[:-1]) >= worth(rule):
        rule = rule[:-1]
    return rule


def learn(sample: list[tuple[dict, bool, int]]) -> list[Rule]:
    """Rules for the bad texts among (features, bad, fold 0-2); folds 0 and 1 grow, 2 prunes."""
    rules: list[Rule] = []
    rest = sample
    while len(rules) < MAX_RULES:
        grow, prune = [(x, b) for x, b, k in rest if k < 2], [(x, b) for x, b, k in rest if k == 2]
        rule = _prune(_grow(grow), prune) if grow else ()
        if not rule:
            break
        (p, n), (q, m) = _counts(grow, rule), _counts(prune, rule)
        if p + q < COVERS or p < PRECISION * (p + n) or q < PRECISION * (q + m):
            break
        rules.append(rule)
        rest = [(x, b, k) for x, b, k in rest if not all(c.holds(x) for c in rule)]
    return rules


def verdict(rules: list[Rule], f: Column) -> Column:
    """The list as an ordered conditional: the number (from 1) of the first rule that holds, else 0."""
    if not rules:
        return F.lit(0)
    out = None
    for k, rule in enumerate(rules, 1):
        holds = rule[0].column(f)
        for c in rule[1:]:
            holds = holds & c.column(f)
        out = F.when(holds, k) if out is None else out.when(holds, k)
    return out.otherwise(0)


def learn_from(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", sample: int = SAMPLE) -> list[Rule]:
    """Rules from at most ``sample`` labelled rows (label 0: bad); ids and labels that are null are left out."""
    chosen = labels.select(F.col(id_col).alias("_id"), F.col(label_col).alias("_label")).where("_id is not null and _label is not null").groupBy("_id").agg(F.min("_label").alias("_label"))
    chosen = chosen.orderBy(F.xxhash64("_id"), "_id").limit(sample)
    s = statistics(F.col("_text"))
    rows = (
        docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("_text"))
        .join(F.broadcast(chosen), "_id")  # at most ``sample`` rows
        .withColumn("_s", s)
        .select(base_failed(F.col("_s")).alias("_failed"), "_id", F.pmod(F.xxhash64("_id", F.lit(1)), F.lit(3)).alias("_fold"), (F.col("_label") == 0).alias("_bad"), features(F.col("_text"), F.col("_s")).alias("_f"))
        .collect()
    )
    # A filter on the statistics in the plan would sink below the join and compute them for every text.
    return learn([(r["_f"].asDict(), r["_bad"], r["_fold"]) for r in sorted(rows, key=lambda r: (r["_id"], r["_bad"])) if not r["_failed"]])


def verdicts(text: Column, rules: list[Rule]) -> Column:
    """Struct of the statistics, base_failed, rule (0: none holds) and kept, as one expression that evaluates each part once."""

    def of(s: Column) -> Column:
        failed = base_failed(s)
        parts = [s[k].alias(k) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
        rule = let(features(text, s), lambda f: verdict(rules, f)) if rules else F.lit(0)
        return let(rule, lambda r: F.struct(*parts, failed.alias("base_failed"), r.alias("rule"), (~failed & (r == 0)).alias("kept")))

    return let(statistics(text), of)


def judged(docs: DataFrame, rules: list[Rule], text_col: str = "text", name: str = "_quality") -> DataFrame:
    """``docs`` with a struct column: the statistics, base_failed, rule (0: none holds) and kept.

    A null or empty text has no words and fails the base. Other columns are carried along untouched; none may be called
    ``name``. To filter on it use ``kept``: a plain filter would sink below and evaluate all of it again.
    """
    return docs.withColumn(name, verdicts(F.col(f"`{text_col}`").cast("string"), rules))


def kept(docs: DataFrame, rules: list[Rule], text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that pass. The verdict is exploded from an array of one or none, so it is evaluated once."""
    passed = F.filter(F.array(verdicts(F.col(f"`{text_col}`").cast("string"), rules)), lambda q: q["kept"])
    mark = fresh(docs, "_kept")
    return docs.select("*", F.explode(F.transform(passed, lambda q: F.lit(1))).alias(mark)).drop(mark)


def op1_quality_rules(spark, sf_dir: str) -> DataFrame:
    """Statistics, base verdict and learned verdict of every document."""
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    rules = learn_from(docs, labels)
    return judged(docs.select("doc_id", "text"), rules).select("doc_id", "_quality.*")
