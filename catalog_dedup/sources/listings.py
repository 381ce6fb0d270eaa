"""Product listings derived from the given tables: what each supplier offers, under a title of its own wording."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .tables import load

#: Word -> synonym that some sellers use.
ADJECTIVES = {"small": "mini", "large": "big", "hot": "heated", "cold": "chilled", "old": "vintage", "new": "brandnew", "red": "crimson", "blue": "azure"}
NOUNS = {"gear": "cog", "bolt": "screw", "rod": "bar", "plate": "panel", "ring": "hoop", "widget": "gadget", "gizmo": "device", "anvil": "block"}
SELLERS = 3


def listing_hash(part: Column, supplier: Column) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws("|", part, supplier)), 1, 8), 16, 10).cast("long")


def _synonym(word: Column, table: dict[str, str], use: Column) -> Column:
    return F.when(use, F.coalesce(F.create_map(*[F.lit(x) for kv in table.items() for x in kv])[word], word)).otherwise(word)


def _bit(k: int) -> Column:
    return F.shiftright("h", k) % 2 == 1


def with_titles(rows: DataFrame) -> DataFrame:
    """Adds ``title``; wording depends on the hash alone and never touches the size."""
    words = F.split("p_name", " ")
    adj, noun = _synonym(words[0], ADJECTIVES, _bit(4)), _synonym(words[1], NOUNS, _bit(5))
    brand = F.when(_bit(6), F.replace(F.col("p_brand"), F.lit("#"), F.lit(" no "))).otherwise(F.replace(F.col("p_brand"), F.lit("#"), F.lit("")))
    kind, size = F.col("p_type"), F.concat(F.lit("size "), F.col("p_size").cast("string"))
    join = lambda *xs: F.concat_ws(" ", *xs)
    layout = F.col("h") % 5
    title = (
        F.when(layout == 0, join(brand, adj, noun, kind, size))
        .when(layout == 1, join(adj, noun, brand, size, kind))
        .when(layout == 2, F.lower(F.concat_ws(" - ", join(adj, noun, kind), brand, size)))
        .when(layout == 3, join(F.lit("NEW!"), brand, noun, adj, kind, size, F.lit("fast shipping")))
        .otherwise(F.upper(join(kind, adj, noun, size, F.lit("by"), brand)))
    )
    return rows.withColumn("title", title)


def offers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every (part, supplier) sold, with its lowest unit price."""
    lines = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_extendedprice", "l_quantity")
    sold = lines.groupBy("l_partkey", "l_suppkey").agg(F.min(F.col("l_extendedprice") / F.col("l_quantity")).alias("price"))
    part = load(spark, sf_dir, "part", "p_partkey", "p_name", "p_brand", "p_type", "p_size")
    rows = sold.join(part, F.col("l_partkey") == F.col("p_partkey")).withColumn("h", listing_hash(F.col("l_partkey"), F.col("l_suppkey")))
    return with_titles(rows).select(
        (F.col("l_partkey") * 100000 + F.col("l_suppkey")).alias("listing_id"), F.col("l_partkey").alias("product_key"), F.col("l_suppkey").alias("seller"),
        F.concat_ws("/", "p_type", "p_brand").alias("category"), "title", "price", "p_name", "p_brand", "p_type", "p_size", "h",
    )


def offers3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The listings of the three sellers per part with the smallest hash."""
    w = Window.partitionBy("product_key").orderBy("h", "seller")
    return offers(spark, sf_dir).withColumn("k", F.row_number().over(w)).filter(F.col("k") <= SELLERS).drop("k")


def true_classes(listings: DataFrame) -> DataFrame:
    """listing_id, product_key, rep (the product's smallest listing) and n_links (its other listings): the whole truth in a row a listing."""
    sized = listings.groupBy("product_key").agg(F.min("listing_id").alias("rep"), (F.count("*") - 1).alias("n_links"))
    return listings.select("listing_id", "product_key").join(sized, "product_key").select("listing_id", "product_key", "rep", "n_links")


def true_pairs(listings: DataFrame) -> DataFrame:
    """a < b of one product. Grows with the square of a product's sellers: for samples with few sellers each; see ``true_classes``."""
    a, b = (listings.select(F.col("listing_id").alias(x), F.col("product_key").alias(f"k{x}")) for x in "ab")
    return a.join(b, (F.col("ka") == F.col("kb")) & (F.col("a") < F.col("b"))).select("a", "b", F.col("ka").alias("product_key"))


def variant_pairs(listings: DataFrame) -> DataFrame:
    """Pairs of first listings of different parts that share name, brand and type, with what differs."""
    first = listings.groupBy("product_key").agg(F.min("listing_id").alias("listing_id"), *[F.first(c).alias(c) for c in ("p_name", "p_brand", "p_type", "p_size")])
    keys = ["p_name", "p_brand", "p_type"]
    a, b = first.select(*keys, F.col("listing_id").alias("a"), F.col("p_size").alias("sa")), first.select(*keys, F.col("listing_id").alias("b"), F.col("p_size").alias("sb"))
    return a.join(b, keys).filter("a < b").select("a", "b", F.when(F.col("sa") == F.col("sb"), "none").otherwise("size").alias("differs"))
