"""Labelled pairs and their text scores."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import text as tx
from ..sources.listings import true_pairs

#: Products whose hash is a multiple of this are for testing, the others for training (44 to 1).
TEST_EVERY = 45
#: What the two products of a negative pair share, and its name.
NEGATIVES = ((("category",), "same leaf"), (("p_name", "p_brand"), "variant"), (("p_type",), "same type"))


def split_of(product: Column) -> Column:
    h = F.conv(F.substring(F.md5(product.cast("string")), 1, 8), 16, 10).cast("long")
    return F.when(h % TEST_EVERY == 0, "test").otherwise("train")


def labelled(listings: DataFrame) -> DataFrame:
    """a, b, is_match, origin, split. Positives are all pairs of a product; negatives join the first listing of each product to that
    of the next product of its split in the same leaf, of the same name and brand (variants), and of the same type. No product is in
    both splits."""
    rows = listings.withColumn("split", split_of(F.col("product_key")))
    out = true_pairs(listings).select("a", "b", F.lit(True).alias("is_match"), F.lit("same product").alias("origin"), split_of(F.col("product_key")).alias("split"))
    first = rows.groupBy("product_key", "category", "p_name", "p_brand", "p_type", "split").agg(F.min("listing_id").alias("a"))
    for keys, origin in NEGATIVES:
        nxt = first.withColumn("b", F.lead("a").over(Window.partitionBy(*keys, "split").orderBy("a"))).filter("b IS NOT NULL")
        out = out.unionByName(nxt.select("a", "b", F.lit(False).alias("is_match"), F.lit(origin).alias("origin"), "split"))
    return out


def with_scores(pairs: DataFrame, listings: DataFrame) -> DataFrame:
    """Adds pm: the cosine of the hashed titles, per mille, 0 if a title has no token."""
    v = tx.dense_features(listings.select("listing_id", "title"), "listing_id", "title").select("listing_id", "vec")
    a, b = (v.select(F.col("listing_id").alias(k), F.col("vec").alias(f"v{k}")) for k in "ab")
    joined = pairs.join(a, "a").join(b, "b")
    long = F.lit(0).cast("long")
    dot = F.aggregate(F.zip_with("va", "vb", lambda x, y: x * y), long, lambda s, x: s + x)
    norm = lambda c: F.aggregate(c, long, lambda s, x: s + x * x)
    joined = joined.withColumns({"dot": dot, "n2": norm("va") * norm("vb")})
    pm = F.when(F.col("n2") > 0, F.floor(1000 * F.col("dot") / F.sqrt(F.col("n2").cast("double")))).otherwise(0).cast("long")
    return joined.withColumn("pm", pm).drop("va", "vb", "n2")
