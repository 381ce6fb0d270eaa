"""Duplicates into products, and the best offer of each."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.formats import written

MOST_MEMBERS = 1000


def groups(pairs: DataFrame) -> DataFrame:
    """id, group_id (smallest id reachable over pairs a, b): labels spread to neighbours and jump to their label's label until
    nothing changes; every round is written, so lineage stays short."""
    both = written(pairs.select("a", "b").union(pairs.select("b", "a")).toDF("u", "v").filter("u != v").distinct())
    labels = written(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("label")))
    while True:
        near = both.join(labels.withColumnRenamed("u", "w"), F.col("v") == F.col("w")).groupBy("u").agg(F.min("label").alias("near"))
        new = labels.join(near, "u").select("u", F.least("label", "near").alias("label"), F.col("label").alias("old"))
        jump = new.select(F.col("u").alias("j"), F.col("label").alias("jumped"))
        new = new.join(jump, F.col("label") == F.col("j"), "left").select("u", F.least("label", F.coalesce("jumped", "label")).alias("label"), "old")
        new = written(new)
        if new.filter("label != old").isEmpty():
            return new.select(F.col("u").alias("id"), F.col("label").alias("group_id"))
        labels = new.drop("old")


def oversized(found: DataFrame, most: int = MOST_MEMBERS) -> DataFrame:
    """Groups of more than ``most`` members, to be looked at and not merged silently."""
    return found.groupBy("group_id").agg(F.count("*").alias("n")).filter(F.col("n") > most)


def buy_box(offers: DataFrame, sellers: DataFrame) -> DataFrame:
    """product_key, listing_id, price, n_offers: lowest price, then the higher account balance, then the smaller id."""
    o = offers.join(sellers, F.col("seller") == F.col("s_suppkey"))
    w = Window.partitionBy("product_key")
    best = o.withColumns({"r": F.row_number().over(w.orderBy("price", F.desc("s_acctbal"), "listing_id")), "n_offers": F.count("*").over(w)})
    return best.filter("r = 1").select("product_key", "listing_id", "price", "n_offers")


def effect(rows: DataFrame) -> DataFrame:
    """One row about listings with their group (g, price, product_key): how many there are before and after grouping, the largest
    group, listings dearer than their group's best price, and groups that mix products."""
    by = rows.groupBy("g").agg(F.count("*").alias("n"), F.min("price").alias("best"), (F.min("product_key") != F.max("product_key")).alias("mixed"))
    j = rows.select("g", "price").join(by.select("g", "best"), "g").agg(F.sum((F.col("price") > F.col("best")).cast("long")).alias("dearer"))
    return by.agg(F.sum("n").alias("listings"), F.count("*").alias("products"), F.max("n").alias("largest"), F.count_if(F.col("mixed")).alias("impure")).crossJoin(j)  # one row each
