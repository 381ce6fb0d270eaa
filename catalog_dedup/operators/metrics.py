"""Measures of accuracy and cost."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def _ratio(a: Column, b: Column) -> Column:
    """a / b, null where b is 0."""
    return F.when(b > 0, a / b)


def confusion(df: DataFrame, truth: str, verdict: str, *by: str) -> DataFrame:
    t, v = F.col(truth), F.col(verdict)
    count = lambda c: F.sum(F.when(c, 1).otherwise(0)).cast("long")
    return df.groupBy(*by).agg(count(t & v).alias("tp"), count(~t & v).alias("fp"), count(t & ~v).alias("fn"), count(~t & ~v).alias("tn"))


def class_report(df: DataFrame, truth: str, verdict: str, *by: str) -> DataFrame:
    """Precision, recall and F1 of Match and Not-Match, both from one matrix."""
    c = confusion(df, truth, verdict, *by)
    part = lambda name, tp, fp, fn: F.struct(F.lit(name).alias("class"), F.col(tp).alias("hits"), F.col(fp).alias("false_alarms"), F.col(fn).alias("misses"))
    r = c.select(*by, F.explode(F.array(part("match", "tp", "fp", "fn"), part("not_match", "tn", "fn", "fp"))).alias("x")).select(*by, "x.*")
    h, f, m = F.col("hits"), F.col("false_alarms"), F.col("misses")
    return r.withColumns({"precision": _ratio(h, h + f), "recall": _ratio(h, h + m), "f1": _ratio(2 * h, 2 * h + f + m)})


def macro_f1(report: DataFrame, *by: str) -> DataFrame:
    """Unweighted mean of the two class F1s."""
    return report.groupBy(*by).agg((F.sum("f1") / 2).alias("macro_f1"))


def sweep(df: DataFrame, score: str, truth: str) -> DataFrame:
    """cut, tp, fp, fn, precision, recall, f1 for the verdict score >= cut at every distinct score. Counts per score are summed
    first, so the running window has a row per distinct score; quantise scores where there are many."""
    at = df.groupBy(F.col(score).alias("cut")).agg(F.sum(F.col(truth).cast("long")).alias("p"), F.count("*").alias("n"))
    w = Window.orderBy(F.desc("cut"))
    s = at.withColumns({"tp": F.sum("p").over(w), "upto": F.sum("n").over(w), "all_p": F.sum("p").over(Window.partitionBy())})
    s = s.withColumns({"fp": F.col("upto") - F.col("tp"), "fn": F.col("all_p") - F.col("tp")})
    return s.select("cut", "tp", "fp", "fn", _ratio(F.col("tp"), F.col("upto")).alias("precision"), _ratio(F.col("tp"), F.col("all_p")).alias("recall"), _ratio(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")).alias("f1"))


def recall_at(hits: DataFrame, exact: DataFrame) -> DataFrame:
    """found, wanted: how many exact neighbours (q, c) the hits hold."""
    return exact.select("q", "c").join(hits.select("q", "c").withColumn("hit", F.lit(1)), ["q", "c"], "left").agg(F.count("hit").alias("found"), F.count("*").alias("wanted"))


GIB = 2**30


def footprint(n: int, d: int, lists: int = 0, links: int = 0) -> int:
    """Bytes of an index: float32 vectors, ids, centroids and graph links (ids)."""
    return 4 * n * d + 8 * n + 4 * lists * d + 8 * n * links


def modelled_gib(n: int, d: int, fixed: float = 0.61, slope: float = 1.025) -> float:
    """Fixed cost plus slope times the float32 payload, in GiB: the line through the published end points."""
    return fixed + slope * (4 * n * d / GIB)
