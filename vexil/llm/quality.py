"""Operator 7: quality rules with risk-controlled thresholds.

Every rule rejects documents whose signal lies above a cutoff. Cutoffs are chosen on the
labelled holdout, per stratum (language): going from the most lenient cutoff to
stricter ones, a cutoff is certified while the exact binomial bound says that at most
`risk` of the good documents lie above it, at level `delta` / (strata x rules) (Bonferroni
over strata and rules; the fixed order within a rule needs no further correction). The walk
stops at the first cutoff that isn't certified. A rule without a certified cutoff is
off in that stratum, so strata without enough labels reject nothing.

All of it is DataFrame functions over whole texts; the holdout statistics cover every
labelled row.

Cases: null text has no words (base_failed); null language is a stratum of its own; labels
for unknown documents and null labels are ignored; several labels of a document count each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_RE, materialise

BLANKS = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
TERMS = 2_000

# Cutoffs of each rule, from lenient to strict, in millionths.
CUTOFFS = {
    "symbols_per_word": [3_000_000, 2_000_000, 1_000_000, 500_000, 200_000, 100_000, 50_000],
    "mean_word_chars": [16_000_000, 12_000_000, 10_000_000, 9_000_000, 8_500_000, 8_000_000],
    "duplicate_line_share": [900_000, 700_000, 500_000, 300_000, 200_000, 100_000],
    "repeated_word_share": [180_000, 120_000, 80_000, 40_000, 20_000],
}


def _let(value: Column, body) -> Column:
    """body(value) with value evaluated once for a row."""
    return F.transform(F.array(value), body)[0]


def repeated_words(words: Column, k: int = 5) -> Column:
    """Words that lie in a window of k words which the same text holds twice or more."""
    n = F.size(words) - (k - 1)
    codes = F.transform(F.sequence(F.lit(0), F.greatest(n, F.lit(1)) - 1), lambda i: F.xxhash64(*(F.get(words, i + j) for j in range(k))))

    def places(h: Column) -> Column:
        ordered = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

        def twins(s: Column) -> Column:
            hit = F.filter(s, lambda x, i: (x["h"] == F.get(s, i - 1)["h"]).eqNullSafe(F.lit(True)) | (x["h"] == F.get(s, i + 1)["h"]).eqNullSafe(F.lit(True)))
            return F.array_sort(F.transform(hit, lambda x: x["i"]))

        covered = F.aggregate(
            _let(ordered, twins), F.struct(F.lit(0).alias("n"), F.lit(-k).alias("last")), lambda s, i: F.struct((s["n"] + F.least(F.lit(k), i - s["last"])).alias("n"), i.alias("last")), lambda s: s["n"]
        )
        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(covered)

    return F.when(n < 2, F.lit(0)).otherwise(_let(codes, places)).cast("bigint")


def measures(docs: DataFrame) -> DataFrame:
    """doc_id, lang, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of every document."""
    text = F.coalesce("text", F.lit(""))
    shown = docs.select("doc_id", "lang", text.alias("t"), F.regexp_extract_all(text, F.lit(WORD_RE), F.lit(0)).alias("w"))
    lines = F.filter(F.split("t", "\n", -1), lambda x: F.translate(x, BLANKS, "") != "")
    return shown.select(
        "doc_id", "lang", F.size("w").cast("bigint").alias("n_words"), F.length(F.translate("t", BLANKS, "")).cast("bigint").alias("word_chars"),
        (F.length("t") - F.length(F.translate("t", SYMBOLS, ""))).cast("bigint").alias("n_symbols"),
        _let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("bigint").alias("n_dup_lines"),
        F.size(lines).cast("bigint").alias("n_lines"), repeated_words(F.col("w")).alias("n_repeat_words"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def signals() -> dict[str, Column]:
    """Each rule's signal in whole millionths, so that cutoffs compare exactly."""

    def share(a: str, b: str) -> Column:
        return F.when(F.col(b) > 0, F.expr(f"{a} * 1000000L div {b}")).otherwise(F.lit(0)).cast("bigint")

    return {"symbols_per_word": share("n_symbols", "n_words"), "mean_word_chars": share("word_chars", "n_words"), "duplicate_line_share": share("n_dup_lines", "n_lines"), "repeated_word_share": share("n_repeat_words", "n_words")}


def _ln_choose(n: Column, x: Column) -> Column:
    def lgamma(z: Column) -> Column:  # Stirling's series, after a shift by 8
        low = F.log(z * (z + 1) * (z + 2) * (z + 3)) + F.log((z + 4) * (z + 5) * (z + 6) * (z + 7))
        y = z + 8
        return (y - 0.5) * F.log(y) - y + 0.9189385332046727 + 1 / (12 * y) - 1 / (360 * y * y * y) + 1 / (1260 * y * y * y * y * y) - low

    return lgamma(n + 1) - lgamma(x + 1) - lgamma(n - x + 1)


def binomial_tail(n: Column, x: Column, p: float) -> Column:
    """P(Bin(n, p) <= x) for x <= p * n: TERMS terms from x downwards, and an upper bound of what is below them."""
    first = F.exp(_ln_choose(n, x) + x * F.log(F.lit(p)) + (n - x) * F.log(F.lit(1 - p)))
    start = F.struct(first.alias("sum"), first.alias("term"), x.cast("double").alias("i"))

    def add(s: Column, _: Column) -> Column:
        term = s["term"] * s["i"] * (1 - p) / ((n - s["i"] + 1) * p)
        return F.struct((s["sum"] + term).alias("sum"), term.alias("term"), (s["i"] - 1).alias("i"))

    def close(s: Column) -> Column:
        ratio = s["i"] * (1 - p) / ((n - s["i"] + 1) * p)
        return F.when(s["i"] <= 0, s["sum"]).when(ratio < 1, s["sum"] + s["term"] * ratio / (1 - ratio)).otherwise(F.lit(1.0))

    steps = F.least(x.cast("int"), F.lit(TERMS))
    return F.when(x <= p * n, F.aggregate(F.when(steps > 0, F.sequence(F.lit(1), F.greatest(steps, F.lit(1)))).otherwise(F.array().cast("array<int>")), start, add, close)).otherwise(F.lit(1.0))


def certify(holdout: DataFrame, risk: float = 0.02, delta: float = 0.05) -> DataFrame:
    """lang, rule, cutoff (millionths): the strictest certified cutoff per stratum and rule.

    holdout: lang and one bigint column for each rule, of the good documents only.
    """
    rules = list(CUTOFFS)
    counts = holdout.groupBy("lang").agg(F.count("*").alias("n"), *(F.sum((F.col(r) > c).cast("int")).alias(f"{r}:{i}") for r in rules for i, c in enumerate(CUTOFFS[r])))
    tests = counts.select("lang", "n", F.explode(F.array(*(F.struct(F.lit(r).alias("rule"), F.lit(i).alias("step"), F.lit(c).cast("bigint").alias("cutoff"), F.col(f"`{r}:{i}`").alias("x")) for r in rules for i, c in enumerate(CUTOFFS[r])))).alias("t")).select("lang", "n", "t.*")
    strata = F.count_distinct("g").alias("strata")
    level = counts.select(F.coalesce(F.col("lang"), F.lit("\0null")).alias("g")).agg(strata)
    tested = tests.crossJoin(F.broadcast(level)).withColumn("p", binomial_tail(F.col("n").cast("double"), F.col("x").cast("double"), risk))
    walk = Window.partitionBy("lang", "rule").orderBy("step")
    passed = tested.withColumn("ok", F.min((F.col("p") <= delta / (F.col("strata") * len(rules))).cast("int")).over(walk))
    return passed.where("ok = 1").groupBy("lang", "rule").agg(F.min_by("cutoff", F.struct(-F.col("step"))).alias("cutoff"))


def apply_rules(docs: DataFrame, labels: DataFrame, risk: float = 0.02, delta: float = 0.05) -> DataFrame:
    """measures plus base_failed, failed_rules (array) and kept. labels: doc_id, quality (1 is good)."""
    scored = materialise(measures(docs).withColumns(signals()), "quality")
    good = labels.where("quality = 1").select("doc_id")
    cutoffs = certify(scored.join(good, "doc_id"), risk, delta)
    table = cutoffs.groupBy("lang").agg(*(F.max(F.when(F.col("rule") == r, F.col("cutoff"))).alias(f"cut_{r}") for r in CUTOFFS)).withColumnRenamed("lang", "_lang")
    judged = scored.join(table, F.col("lang").eqNullSafe(F.col("_lang")), "left")
    broken = F.filter(F.array(*(F.when(F.col(r) > F.col(f"cut_{r}"), F.lit(r)) for r in CUTOFFS)), lambda x: x.isNotNull())
    return judged.withColumn("base_failed", base_failed()).withColumn("failed_rules", broken).withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0)).drop("_lang")
