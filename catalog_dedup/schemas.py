"""Schemas of the engine's own tables."""

from pyspark.sql import types as T

LISTING = T.StructType([
    T.StructField("listing_id", T.LongType()), T.StructField("product_key", T.LongType()), T.StructField("seller", T.LongType()),
    T.StructField("category", T.StringType()), T.StructField("title", T.StringType()), T.StructField("price", T.DoubleType()),
])
CANDIDATE = T.StructType([T.StructField("q", T.LongType()), T.StructField("c", T.LongType()), T.StructField("score", T.DoubleType()), T.StructField("rank", T.IntegerType())])
LABELLED_PAIR = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType()), T.StructField("is_match", T.BooleanType()), T.StructField("origin", T.StringType())])
EVENT = T.StructType([
    T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()),
    T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType()),
])
