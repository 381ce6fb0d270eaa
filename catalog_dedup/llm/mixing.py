"""Mixing sources to target weights.

Each document gets a hash-random key. Rows are range-sorted by key within each source (ranges are the top bits of the
key, so a hot source spreads over many tasks), prefix sums of sizes are summed over ranges and then within each, and the
source's budget cuts them at one key. Whole epochs are taken first, the rest of the budget up to the cut, where the last
document is taken in part, so that a source's words meet its target to the word.

Targets: sources in code-point order (null last) weigh ``weights`` in turn and share ``share`` of all words; none goes
beyond ``most`` times its words, and what is left over is shared anew by weight.

Only DataFrame functions run. Null and blank texts have size 0 and are taken for 0 words. Rows that repeat another in
doc_id and text share its key; at the cut they divide what is left in proportion (rounded down). An empty table gives no
rows. Input columns named like a result column are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import small, stash, words

WEIGHTS = (3, 1, 2)
SHARE = 1.5
MOST = 2
#: Key ranges a source is dealt into: the top bits of a key of 60.
RANGE_BITS = 12


def key(doc_id: Column, text: Column) -> Column:
    """60 hash bits of id and text."""
    none = F.lit("")
    digest = F.md5(F.concat(F.coalesce(doc_id.cast("string"), none), F.lit("|"), F.md5(F.coalesce(text, none))))
    return F.conv(F.substring(digest, 1, 15), 16, 10).cast("long")


def targets(sized: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """source, source_size and target of each source. The unpartitioned windows sort one row per source."""
    by = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    turn = (F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1) % len(weights)
    s = by.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), turn + 1)).withColumn("cap", most * F.col("source_size"))
    w = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    s = s.withColumns({"total": F.sum("source_size").over(Window.partitionBy()), "capped": F.coalesce(F.sum("cap").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)), "left": F.sum("weight").over(w.rowsBetween(0, Window.unboundedFollowing))})
    rate = (F.col("total") * share - F.col("capped")) / F.col("left")
    s = s.withColumn("rate", F.min(F.when(rate * F.col("weight") <= F.col("cap"), F.struct(F.col("cap") / F.col("weight"), rate))).over(Window.partitionBy())["col2"])
    target = F.least(F.col("cap").cast("double"), F.coalesce(F.col("rate") * F.col("weight"), F.col("cap").cast("double")))
    return s.select("source", "source_size", target.alias("target"))


def plan(sized: DataFrame, **options) -> DataFrame:
    """One row per source: whole epochs, the cut key, what is left there (rest) and the size of the rows with that key (tie)."""
    goal = targets(sized, **options)
    goal = goal.withColumn("epochs", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
    goal = goal.withColumn("budget", F.floor("target") - F.col("epochs") * F.col("source_size"))
    goal = stash(goal, "targets")
    keyed = sized.filter("size > 0").groupBy("source", "key").agg(F.sum("size").alias("tie")).withColumn("range", F.shiftright("key", 60 - RANGE_BITS))
    in_range = Window.partitionBy("source", "range").orderBy("key").rowsBetween(Window.unboundedPreceding, 0)
    keyed = keyed.withColumn("within", F.sum("tie").over(in_range))
    ranges = keyed.groupBy("source", "range").agg(F.max("within").alias("sum"))
    ahead = Window.partitionBy("source").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    ranges = ranges.withColumn("ahead", F.coalesce(F.sum("sum").over(ahead), F.lit(0)))
    # Of each source only the range that holds the cut is looked into.
    g = goal.select(F.col("source").alias("g_source"), "budget")
    same = F.col("source").eqNullSafe(F.col("g_source"))
    hit = ranges.join(F.broadcast(g) if _few(goal) else g, same).filter("budget > 0 AND ahead < budget AND ahead + sum >= budget").select(F.col("source").alias("h_source"), F.col("range").alias("h_range"), "ahead", "budget")
    hit = small(stash(hit, "cut-ranges"))
    cut = keyed.join(hit, F.col("source").eqNullSafe(F.col("h_source")) & (F.col("range") == F.col("h_range"))).filter("ahead + within >= budget")
    cut = cut.groupBy("source").agg(F.min_by(F.struct("key", "tie", (F.col("budget") - F.col("ahead") - F.col("within") + F.col("tie")).alias("rest")), "key").alias("c"))
    cut = cut.select(F.col("source").alias("c_source"), "c.*")
    return goal.join(cut, F.col("source").eqNullSafe(F.col("c_source")), "left").select(F.col("source").alias("p_source"), "source_size", "target", "epochs", F.col("key").alias("cut"), "tie", "rest")


def _few(df: DataFrame) -> bool:
    return df.limit(100_001).count() <= 100_000


def sized_rows(docs: DataFrame, keep: list[str]) -> DataFrame:
    return docs.select(*[F.col(f"`{c}`") for c in keep], F.col("source"), F.size(words(F.col("text"))).cast("long").alias("size"), key(F.col("doc_id"), F.col("text")).alias("key"))


def _taken() -> Column:
    extra = F.when(F.col("key") < F.col("cut"), F.col("size")).when(F.col("key") == F.col("cut"), F.floor(F.col("rest") * F.col("size") / F.col("tie"))).otherwise(0)
    return (F.col("epochs") * F.col("size") + F.coalesce(extra, F.lit(0))).cast("long")


def mix_sizes(docs: DataFrame, **options) -> DataFrame:
    """doc_id, source, size, source_size, target and taken of every row."""
    sized = stash(sized_rows(docs, ["doc_id"]), "sizes")
    p = small(stash(plan(sized, **options), "mix-plan"))
    out = sized.join(p, F.col("source").eqNullSafe(F.col("p_source")), "left")
    return out.select("doc_id", "source", "size", "source_size", "target", _taken().alias("taken"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """The mixed corpus with the columns of ``docs``: a row per epoch of each document. The one document of a source at its
    cut has its words up to the cut, parted by single spaces (its white space is not kept); all other texts are as they were."""
    sized = stash(sized_rows(docs, []), "sizes")
    p = small(stash(plan(sized, **options), "mix-plan"))
    names = docs.columns
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("_row"), F.col("source"), F.size(words(F.col("text"))).cast("long").alias("size"), key(F.col("doc_id"), F.col("text")).alias("key"))
    rows = rows.join(p, F.col("source").eqNullSafe(F.col("p_source")), "left").withColumn("taken", _taken()).filter("taken > 0")
    copies = F.sequence(F.lit(1).cast("long"), F.ceil(F.col("taken") / F.col("size")))
    rows = rows.select("_row", "size", "taken", F.explode(copies).alias("copy")).withColumn("over", F.col("copy") * F.col("size") - F.col("taken"))
    part = F.array_join(F.slice(words(F.col("_row.text")), F.lit(1), (F.col("size") - F.col("over")).cast("int")), " ")
    text = F.when(F.col("over") > 0, part).otherwise(F.col("_row.text"))
    return rows.select(*[(text if c == "text" else F.col("_row")[c]).alias(c) for c in names])

