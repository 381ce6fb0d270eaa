"""Quality rules with thresholds that adapt to each language and source.

Every document gets integer measures (per mille). A mergeable quantile sketch of each measure is kept per language and
source: counts of log-linear buckets (exact below 128, 64 buckets a power of two above, so a quantile is off by under
1/64). Bucket counts add up, so sketches of sources merge into that of their language and of the corpus; and they are
integers, so reruns and other engines agree. A document is rejected if a measure lies beyond the outer fence of its own
group: the upper quartile plus ``FENCE`` spreads. The spread is the interquartile range, and at least a tenth of the median
and a tenth of a word (100 per mille; what a measure that is zero for most documents goes by): one rule for all measures.
Groups of under ``LEAST_GROUP`` documents use the sketch of their language, languages as small that of the corpus.

Only DataFrame functions run. Null texts count as empty. Null languages and sources are groups of their own. Repeated
rows are judged one by one. Input columns named like a result column, in any case, are replaced; all other names are free. An
empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import carried, others, small, stash, unpacked, words

WINDOW = 8
FENCE = 3
LEAST_GROUP = 50
#: Least spread: 1 in so many of the median, and per mille.
PART, LEAST_SPREAD = 10, 100
MEASURES = ("symbols", "repeats", "capitals", "marks", "dup_lines", "stutters", "word_length")
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def document_measures(docs: DataFrame, keep: list[str]) -> DataFrame:
    """``row`` (the ``keep`` columns of ``docs``), lang and source with the base counts and, as ``m_<name>``, the measures in per mille."""
    t = F.coalesce(F.col("text"), F.lit(""))
    zero = F.lit(0).cast("long")
    lines = F.filter(F.split(t, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    step = docs.select(carried(keep).alias("row"), "lang", "source", "text").withColumns({"_words": words(F.col("text")), "_lines": lines})
    step = step.withColumns({
        "n_words": F.size("_words").cast("long"),
        "word_chars": F.aggregate("_words", zero, lambda a, w: a + F.length(w)),
        "n_symbols": F.length(F.regexp_replace(t, "[^#*$%&|<>]+", "")).cast("long"),
        "n_lines": F.size("_lines").cast("long"),
        "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
        "_capitals": F.length(F.regexp_replace(t, r"[^\p{Lu}]+", "")).cast("long"),
        "_marks": F.length(F.regexp_replace(t, "[^!?]+", "")).cast("long"),
        "_hash": F.transform("_words", lambda w: F.xxhash64(w)),
    }).drop("_words", "_lines", "text")
    step = step.withColumn("_stutters", F.size(F.filter("_hash", lambda h, i: F.coalesce(F.get("_hash", i - 1) == h, F.lit(False)))).cast("long"))
    none = F.array().cast("array<bigint>")
    runs = F.when(F.size("_hash") < WINDOW, none).otherwise(F.transform(F.sequence(F.lit(0), F.size("_hash") - WINDOW), lambda i: F.xxhash64(*[F.get("_hash", i + k) for k in range(WINDOW)])))
    step = step.withColumn("_runs", runs).drop("_hash")
    step = step.withColumn("_repeated", F.size(F.array_distinct("_runs")) < F.size("_runs"))
    # Only documents with a repeated window pay for the sort.
    step = step.withColumn("_sorted", F.when(F.col("_repeated"), F.sort_array(F.transform("_runs", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))).drop("_runs")
    same = lambda x, k: F.coalesce(F.get("_sorted", k)["h"] == x["h"], F.lit(False))
    step = step.withColumn("_starts", F.sort_array(F.transform(F.filter("_sorted", lambda x, k: same(x, k - 1) | same(x, k + 1)), lambda x: x["i"]))).drop("_sorted")
    covered = F.aggregate(F.transform("_starts", lambda p, k: F.least(F.lit(WINDOW), F.coalesce(F.get("_starts", k + 1) - p, F.lit(WINDOW)))), zero, lambda a, x: a + x)
    step = step.withColumn("n_repeat_words", F.coalesce(covered, zero)).drop("_starts", "_repeated")
    rate = lambda a, b: F.expr(f"CASE WHEN {b} = 0 THEN 0 ELSE 1000 * {a} DIV {b} END").cast("long")
    return step.withColumns({
        "m_symbols": rate("n_symbols", "n_words"), "m_repeats": rate("n_repeat_words", "n_words"), "m_capitals": rate("_capitals", "word_chars"),
        "m_marks": rate("_marks", "n_words"), "m_dup_lines": rate("n_dup_lines", "n_lines"), "m_word_length": rate("word_chars", "n_words"),
        "m_stutters": rate("_stutters", "n_words"),
    }).drop("_capitals", "_marks", "_stutters")


def bucket(value: Column) -> Column:
    """Lower end of the value's sketch bucket."""
    shift = F.greatest(F.length(F.bin(value)) - 7, F.lit(0))
    return F.call_function("shiftleft", F.call_function("shiftright", value, shift), shift)


def sketches(measured: DataFrame) -> DataFrame:
    """lang, source, measure, bucket, n: the quantile sketches, one per language, source and measure. Only documents that pass the base rules count."""
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), bucket(F.col(f"m_{m}")).alias("bucket")) for m in MEASURES]))
    return measured.filter(~base_failed()).select("lang", "source", each.alias("x")).groupBy("lang", "source", "x.measure", "x.bucket").agg(F.count("*").alias("n"))


def fences(sketch: DataFrame, by: list[str]) -> DataFrame:
    """For each group in ``by``: its number of documents and a fence per measure, from merged sketches."""
    merged = sketch.groupBy(*by, "measure", "bucket").agg(F.sum("n").alias("n"))
    w = Window.partitionBy(*by, "measure")
    q = merged.withColumns({"total": F.sum("n").over(w), "below": F.sum("n").over(w.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0))})
    q = q.groupBy(*by, "measure").agg(F.first("total").alias("total"), *[F.min(F.when(F.col("below") * 4 >= F.col("total") * k, F.col("bucket"))).alias(f"q{k}") for k in (1, 2, 3)])
    fence = F.col("q3") + FENCE * F.greatest(F.col("q3") - F.col("q1"), F.expr(f"q2 DIV {PART}"), F.lit(LEAST_SPREAD))
    return q.groupBy(*by).agg(F.max("total").alias("total"), *[F.max(F.when(F.col("measure") == m, fence)).alias(f"f_{m}") for m in MEASURES])


def thresholds(sketch: DataFrame) -> DataFrame:
    """lang, source and a fence per measure for each group, small groups with the fences of their language or of the corpus."""
    names = [f"f_{m}" for m in MEASURES]
    level = lambda by, tag: fences(sketch, by).select(*[F.col(c).alias(f"{tag}_{c}") for c in [*by, "total", *names]])
    own, lang, whole = level(["lang", "source"], "o"), level(["lang"], "l"), level([], "w")
    joined = own.join(lang, F.col("o_lang").eqNullSafe(F.col("l_lang")), "left").join(F.broadcast(whole), F.lit(True), "left")  # one row
    pick = lambda n: F.when(F.col("o_total") >= LEAST_GROUP, F.col(f"o_{n}")).when(F.col("l_total") >= LEAST_GROUP, F.col(f"l_{n}")).otherwise(F.col(f"w_{n}"))
    return joined.select(F.col("o_lang").alias("t_lang"), F.col("o_source").alias("t_source"), *[pick(n).alias(n) for n in names])


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


def apply_rules(docs: DataFrame, keep: list[str]) -> DataFrame:
    """``keep`` columns of ``docs`` (text, lang and source must be there), the base counts, ``base_failed`` and ``kept``."""
    keep = others(keep, [*BASE, "base_failed", "kept"])
    measured = stash(document_measures(docs, keep), "measures")
    limits = small(stash(thresholds(sketches(measured)), "thresholds"))
    out = measured.join(limits, F.col("lang").eqNullSafe(F.col("t_lang")) & F.col("source").eqNullSafe(F.col("t_source")), "left")
    within = F.lit(True)
    for m in MEASURES:
        within &= F.coalesce(F.col(f"m_{m}") <= F.col(f"f_{m}"), F.lit(True))
    failed = base_failed()
    return out.select(*unpacked("row", keep), *BASE, failed.alias("base_failed"), (~failed & within).alias("kept"))
