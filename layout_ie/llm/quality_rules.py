"""Quality rules whose cutoffs are certified on labelled holdouts, as DataFrame expressions only.

Text metrics are computed per document inside one row (no shuffle of words).  For
each stratum and rule a ladder of cutoffs runs from lenient to strict.  A cutoff
is certified when an exact binomial test on the labelled good documents of the
stratum rejects "this cutoff loses more than ``risk`` of the good documents".
The tests of one ladder run in a fixed order and stop at the first failure, which
needs no correction; the level is split evenly over strata and rules
(Bonferroni), and so is the tolerated risk over the rules, so that with
probability ``1 - level`` no stratum loses more than ``risk`` of its good
documents by all rules together.  The base rules are fixed and stand outside that risk.

Defined results: a null text has no words and fails the base rules; a null or
unlabelled stratum has no certified cutoff, so only the base rules apply to it;
labels that are null, repeated or of unknown documents are merged or ignored;
empty tables give empty results; extra columns are not looked at.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD_CHAR, WORD_GAP, let, settle

SYMBOLS = "#*$%&|<>"
GAPS = " \t\n\x0b\x0c\r"
#: Documents below it fail the base rules.
MIN_WORDS = 50
#: Percentage of words in repeated windows above which the base rules fail.
MAX_REPEAT_PERCENT = 50
#: Broadcast the certified cutoffs up to this number of strata, else shuffle.
BROADCAST_STRATA = 50_000


@dataclass(frozen=True)
class Rule:
    """Reject a document if ``metric`` exceeds the cutoff; ``ladder`` goes from lenient to strict."""

    name: str
    metric: str
    ladder: tuple[float, ...]


#: Metrics are ratios, so that long and short documents are judged alike.
RULES = (
    Rule("symbols", "1.0 * n_symbols / greatest(n_words, 1)", (3.0, 2.0, 1.5, 1.0, 0.8, 0.6, 0.4, 0.3, 0.2)),
    Rule("repeats", "1.0 * n_repeat_words / greatest(n_words, 1)", (0.5, 0.45, 0.4, 0.35, 0.3, 0.25, 0.2)),
    Rule("lines", "1.0 * n_dup_lines / greatest(n_lines, 1)", (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3)),
    Rule("long_words", "1.0 * word_chars / greatest(n_words, 1)", (40.0, 30.0, 20.0, 15.0, 12.0)),
    Rule("capitals", "1.0 * n_capitals / greatest(word_chars, 1)", (0.9, 0.8, 0.7, 0.6, 0.5)),
)


def _repeated_words(grams: Column) -> Column:
    """Words inside three-word windows whose hash stands twice or more in ``grams``."""

    def covered(positions: Column) -> Column:
        reach = F.transform(positions, lambda p, i: F.least(F.lit(3), F.coalesce(F.get(positions, i + 1), p + 3) - p))
        return F.aggregate(reach, F.lit(0), lambda total, n: total + n)

    def twice(marked: Column) -> Column:
        hits = F.filter(
            marked,
            lambda s, i: F.coalesce((i > 0) & (F.get(marked, i - 1)["h"] == s["h"]), F.lit(False))
            | F.coalesce(F.get(marked, i + 1)["h"] == s["h"], F.lit(False)),
        )
        return let(F.sort_array(F.transform(hits, lambda s: s["i"])), covered)

    some = F.size(F.array_distinct(grams)) < F.size(grams)
    marked = F.sort_array(F.transform(grams, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    return F.when(some, let(marked, twice)).otherwise(0)


def text_metrics(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Counts of each whole text, one row per input row: no shuffle, no Python.

    Three-word windows are compared by a 64-bit hash within one document.
    """
    base = docs.select(*keep, F.coalesce(F.col(text), F.lit("")).alias("_text"))
    words = base.select(
        *keep,
        "_text",
        F.array_remove(F.split("_text", WORD_GAP), "").alias("_words"),
        F.filter(F.split("_text", "\n"), lambda line: line.rlike(WORD_CHAR)).alias("_lines"),
    )
    n = F.size("_words")
    grams = words.select(
        *keep,
        n.cast("long").alias("n_words"),
        F.length(F.translate("_text", GAPS, "")).cast("long").alias("word_chars"),
        (F.length("_text") - F.length(F.translate("_text", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        (F.length("_text") - F.length(F.translate("_text", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", ""))).cast("long").alias("n_capitals"),
        F.size("_lines").cast("long").alias("n_lines"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
        F.when(
            n >= 3,
            let(
                F.col("_words"),
                lambda w: F.transform(F.slice(w, F.lit(1), F.size(w) - 2), lambda a, i: F.xxhash64(a, F.get(w, i + 1), F.get(w, i + 2))),
            ),
        )
        .otherwise(F.array().cast("array<bigint>"))
        .alias("_grams"),
    )
    return grams.select(
        *keep, "n_words", "word_chars", "n_symbols", "n_capitals", "n_lines", "n_dup_lines",
        _repeated_words(F.col("_grams")).cast("long").alias("n_repeat_words"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))


def _log_tail(n: Column, k: Column, risk: float) -> Column:
    """ln P(X <= k) for X ~ Binomial(n, risk), summed term by term in logarithms."""
    import math

    odds = math.log(risk) - math.log1p(-risk)
    first = n * F.lit(math.log1p(-risk))

    def step(acc: Column, j: Column) -> Column:
        term = acc["term"] + F.log((n - j + 1) / j) + F.lit(odds)
        top = F.greatest(acc["total"], term)
        return F.struct(term.alias("term"), (top + F.log(F.exp(acc["total"] - top) + F.exp(term - top))).alias("total"))

    start = F.struct(first.alias("term"), first.alias("total"))
    steps = F.when(k > 0, F.sequence(F.lit(1).cast("long"), k)).otherwise(F.array().cast("array<bigint>"))
    return F.aggregate(steps, start, step, lambda acc: acc["total"])


def certify(scored: DataFrame, labels: DataFrame, stratum: str, rules: tuple[Rule, ...] = RULES, risk: float = 0.05, level: float = 0.05) -> DataFrame:
    """One row per stratum with the strictest certified cutoff of each rule (null: none).

    ``scored`` has ``doc_id``, the stratum and the metrics; ``labels`` has
    ``doc_id``, ``quality`` and ``toxic``: good is quality 1 and not toxic.
    """
    import math

    good = (
        labels.where(F.col("doc_id").isNotNull())
        .groupBy("doc_id")
        .agg(F.min("quality").alias("_quality"), F.max("toxic").alias("_toxic"))
        .where((F.col("_quality") == 1) & (F.coalesce("_toxic", F.lit(0)) == 0))
        .select("doc_id")
    )
    held = scored.where(~base_failed() & F.col(stratum).isNotNull()).join(good, "doc_id", "left_semi")
    counts = held.groupBy(stratum).agg(
        F.count("*").alias("n"),
        *(F.count(F.when(F.expr(r.metric) > c, 1)).alias(f"k_{r.name}_{i}") for r in rules for i, c in enumerate(r.ladder)),
    )
    counts = settle(counts, "holdout")
    strata = max(1, counts.count())
    each, mark = risk / len(rules), math.log(level / (strata * len(rules)))
    picked = []
    for r in rules:
        best = F.lit(None).cast("double")
        for i in reversed(range(len(r.ladder))):
            passed = F.lit(True)
            for j in range(i + 1):  # every more lenient cutoff must have passed as well
                passed = passed & (F.col(f"k_{r.name}_{j}") <= each * F.col("n")) & (F.col(f"p_{r.name}_{j}") <= mark)
            best = F.coalesce(best, F.when(passed, F.lit(float(r.ladder[i]))))
        picked.append(best.alias(f"cut_{r.name}"))
    tails = counts.select(
        stratum, "n",
        *(c for r in rules for i in range(len(r.ladder)) for k in [F.col(f"k_{r.name}_{i}")]
          for c in (k, F.when(k <= each * F.col("n"), _log_tail(F.col("n"), k, each)).otherwise(0.0).alias(f"p_{r.name}_{i}"))),
    )
    return tails.select(stratum, F.col("n").alias("n_holdout"), *picked)


def judge(scored: DataFrame, cutoffs: DataFrame, stratum: str, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Adds ``base_failed``, ``failed_rules`` and ``kept``; the cutoffs travel to the rows, not the rows to the strata."""
    cuts = cutoffs.select(F.col(stratum).alias("_stratum"), *(F.col(f"cut_{r.name}") for r in rules))
    cuts = settle(cuts, "cutoffs")
    if cuts.count() <= BROADCAST_STRATA:
        cuts = F.broadcast(cuts)
    joined = scored.join(cuts, F.col(stratum) == F.col("_stratum"), "left").drop("_stratum")
    failed = F.array_compact(F.array(*(F.when(F.expr(r.metric) > F.col(f"cut_{r.name}"), F.lit(r.name)) for r in rules)))
    return (
        joined.withColumn("base_failed", base_failed())
        .withColumn("failed_rules", failed)
        .withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))
        .drop(*(f"cut_{r.name}" for r in rules))
    )


def apply_rules(docs: DataFrame, labels: DataFrame, stratum: str = "lang", risk: float = 0.05, level: float = 0.05) -> DataFrame:
    """Metrics and verdict of every document, cutoffs certified on the labelled ones."""
    scored = settle(text_metrics(docs, keep=("doc_id", stratum)), "metrics")
    return judge(scored, certify(scored, labels, stratum, risk=risk, level=level), stratum)


def stage(docs: DataFrame, labels: DataFrame, stratum: str = "lang") -> DataFrame:
    """The documents that pass, in their own columns.

    Texts are measured once and written beside their metrics, so that the
    cutoffs read numbers only and no text is shuffled.
    """
    names = {c: f"_own_{i}" for i, c in enumerate(docs.columns)}
    inner = docs.select("*").withColumns({f"_own_{i}": F.col(f"`{c}`") for i, c in enumerate(docs.columns)})
    inner = inner.select(*names.values(), *(F.col(names[c]).alias(c) for c in ("doc_id", stratum, "text")))
    scored = settle(text_metrics(inner, keep=(*names.values(), "doc_id", stratum)), "measured")
    cutoffs = certify(scored, labels, stratum)
    return judge(scored, cutoffs, stratum).where("kept").select(*(F.col(v).alias(k) for k, v in names.items()))
