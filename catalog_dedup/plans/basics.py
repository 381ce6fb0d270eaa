"""Titles, catalogue profiles and the joins, windows and aggregates around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import text as tx
from ..operators import baselines
from ..sources import listings
from ..sources.tables import load
from . import sql
from .registry import query

TOK = r"[\p{L}\p{N}]+"


@query(r"SELECT doc_id, trim(regexp_replace(lower(text), '[^\p{L}\p{N}]+', ' ', 'g')) AS title FROM documents")
def title_normalise(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents", "doc_id", "text").select("doc_id", tx.normalise(F.col("text")).alias("title"))


@query(rf"SELECT doc_id, array_to_string(regexp_extract_all(lower(text), '{TOK}')[1:32], ' ') AS head, len(regexp_extract_all(lower(text), '{TOK}')[1:32])::BIGINT AS n FROM documents")
def first_tokens_32(spark: SparkSession, sf: str) -> DataFrame:
    head = tx.first_tokens(F.col("text"))
    return load(spark, sf, "documents", "doc_id", "text").select("doc_id", F.array_join(head, " ").alias("head"), F.size(head).cast("long").alias("n"))


def _coverage_sql(relation: str, text: str, source: str) -> str:
    return rf"SELECT '{source}' AS source, budget, count(*) AS n_rows, sum((n <= budget)::BIGINT)::BIGINT AS n_covered FROM (SELECT len(regexp_extract_all(lower({text}), '{TOK}')) AS n FROM {relation}), (SELECT unnest([8, 16, 32, 64]) AS budget) GROUP BY budget"


@query(f"WITH {sql.OFFERS} {_coverage_sql('documents', 'text', 'documents')} UNION ALL {_coverage_sql('offers', 'title', 'offers')} UNION ALL {_coverage_sql('benchmark', 'text', 'benchmark')}")
def token_budget_coverage(spark: SparkSession, sf: str) -> DataFrame:
    """Share of texts that fit 8, 16, 32 and 64 tokens."""
    parts = [("documents", load(spark, sf, "documents", "text")), ("offers", listings.offers(spark, sf).select(F.col("title").alias("text"))), ("benchmark", load(spark, sf, "benchmark", "text"))]
    made = [tx.budget_coverage(df, "text").select(F.lit(n).alias("source"), "budget", "n_rows", "n_covered") for n, df in parts]
    return made[0].unionByName(made[1]).unionByName(made[2])


@query(rf"WITH t AS (SELECT unnest(regexp_extract_all(lower(text), '{TOK}')) AS token FROM documents) SELECT token, count(*) AS n FROM t GROUP BY token ORDER BY n DESC, token LIMIT 200")
def vocab_top(spark: SparkSession, sf: str) -> DataFrame:
    return tx.fit_vocabulary(load(spark, sf, "documents", "text"), "text", 200)


@query(r"SELECT page_id, replace(replace(replace(trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)), '&lt;', '<'), '&gt;', '>'), '&amp;', '&') AS title FROM pages")
def page_titles(spark: SparkSession, sf: str) -> DataFrame:
    t = F.trim(F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1))
    for entity, plain in (("&lt;", "<"), ("&gt;", ">"), ("&amp;", "&")):
        t = F.replace(t, F.lit(entity), F.lit(plain))
    return load(spark, sf, "pages", "page_id", "html").select("page_id", t.alias("title"))


@query("SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_quantity BETWEEN 5 AND 20 AND l_returnflag IN ('A', 'R') AND p_brand LIKE 'Brand#1%' AND p_size IS NOT NULL AND l_shipdate >= TIMESTAMP '1996-01-01'")
def rule_filter(spark: SparkSession, sf: str) -> DataFrame:
    lines = load(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_returnflag", "l_shipdate")
    lines = lines.filter(F.col("l_quantity").between(5, 20) & F.col("l_returnflag").isin("A", "R") & (F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp_ntz")))
    part = load(spark, sf, "part", "p_partkey", "p_brand", "p_size").filter(F.col("p_brand").like("Brand#1%") & F.col("p_size").isNotNull())
    return lines.join(part, F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "l_linenumber", "l_partkey")


@query(f"WITH {sql.OFFERS} SELECT listing_id, product_key, seller, category, title, price, n_name AS nation FROM offers JOIN supplier ON seller = s_suppkey JOIN nation ON s_nationkey = n_nationkey")
def offer_listings(spark: SparkSession, sf: str) -> DataFrame:
    sellers = load(spark, sf, "supplier", "s_suppkey", "s_nationkey").join(load(spark, sf, "nation", "n_nationkey", "n_name"), F.col("s_nationkey") == F.col("n_nationkey"))
    rows = listings.offers(spark, sf).join(sellers, F.col("seller") == F.col("s_suppkey"))
    return rows.select("listing_id", "product_key", "seller", "category", "title", "price", F.col("n_name").alias("nation"))


@query(rf"SELECT d.doc_id, d.source FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.doc_id IS NULL")
def unmatched_listings(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents", "doc_id", "source").join(load(spark, sf, "labels", "doc_id"), "doc_id", "left_anti")


@query("SELECT coalesce(d.source, '-') AS source, count(d.doc_id) AS n_docs, count(l.doc_id) AS n_labels, sum(l.quality)::BIGINT AS n_good FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY ALL")
def label_report(spark: SparkSession, sf: str) -> DataFrame:
    d = load(spark, sf, "documents", "doc_id", "source")
    lab = load(spark, sf, "labels", "doc_id", "quality").withColumnRenamed("doc_id", "l_id")
    j = d.join(lab, F.col("doc_id") == F.col("l_id"), "full")
    return j.groupBy(F.coalesce("source", F.lit("-")).alias("source")).agg(F.count("doc_id").alias("n_docs"), F.count("l_id").alias("n_labels"), F.sum("quality").alias("n_good"))


@query("SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_partkey < b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) <= 10")
def price_band_join(spark: SparkSession, sf: str) -> DataFrame:
    """Range join: bands of the radius, each row looked up in its own band and the two beside it."""
    p = load(spark, sf, "part", "p_partkey", "p_brand", "p_type", "p_retailprice").withColumn("band", F.floor(F.col("p_retailprice") / 10))
    a = p.select("p_brand", "p_type", F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("pa"), F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"))
    b = p.select("p_brand", "p_type", F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("pb"), "band")
    return a.join(b, ["p_brand", "p_type", "band"]).filter((F.col("a") < F.col("b")) & (F.abs(F.col("pa") - F.col("pb")) <= 10)).select("a", "b")


@query("SELECT event_id, user_id, prev_id FROM (SELECT event_id, user_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev_id FROM events) WHERE event_type <> 'view'")
def asof_latest_event(spark: SparkSession, sf: str) -> DataFrame:
    """As-of join: for every other event the user's latest earlier view."""
    e = load(spark, sf, "events", "event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("prev_id", last).filter("event_type != 'view'").select("event_id", "user_id", "prev_id")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def interval_join_events(spark: SparkSession, sf: str) -> DataFrame:
    e = load(spark, sf, "events", "event_id", "user_id", "ts").withColumn("slot", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_800_000_000))
    a = e.select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"), F.explode(F.array("slot", F.col("slot") + 1)).alias("slot"))
    b = e.select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"), "slot")
    return a.join(b, ["user_id", "slot"]).filter("tb > ta AND tb <= ta + INTERVAL 30 MINUTE").select("a", "b")


@query(rf"""WITH t AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '{TOK}')) AS tok FROM documents)
SELECT tok AS k, min(doc_id) OVER w AS rep, doc_id AS id FROM t WINDOW w AS (PARTITION BY tok) QUALIFY count(*) OVER w > 1""")
def shared_token_block(spark: SparkSession, sf: str) -> DataFrame:
    """Blocks of texts that share a token, with all members: as many rows as distinct tokens of texts, whatever a token's frequency."""
    t = load(spark, sf, "documents", "doc_id", "text").select(F.col("doc_id").alias("id"), F.explode(F.array_distinct(tx.tokens(F.col("text")))).alias("k"))
    return baselines.blocks(t)


@query(f"WITH {sql.OFFERS} SELECT category, count(*) AS n_listings, count(DISTINCT product_key) AS n_products, count(DISTINCT seller) AS n_sellers, min(price) AS least, max(price) AS most FROM offers GROUP BY category")
def catalogue_profile(spark: SparkSession, sf: str) -> DataFrame:
    o = listings.offers(spark, sf)
    return o.groupBy("category").agg(F.count("*").alias("n_listings"), F.countDistinct("product_key").alias("n_products"), F.countDistinct("seller").alias("n_sellers"), F.min("price").alias("least"), F.max("price").alias("most"))


@query("SELECT lang, count(DISTINCT source) AS n_sources, count(DISTINCT text) AS n_texts, count(*) AS n FROM documents GROUP BY lang")
def distinct_profile(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents", "lang", "source", "text").groupBy("lang").agg(F.countDistinct("source").alias("n_sources"), F.countDistinct("text").alias("n_texts"), F.count("*").alias("n"))


@query(f"WITH {sql.OFFERS} SELECT category, count(DISTINCT listing_id) AS listings, true AS within FROM offers GROUP BY category")
def approximate_distinct(spark: SparkSession, sf: str) -> DataFrame:
    """Distinct listings of each category, and whether a sketch with 2 % deviation comes within 10 % of them."""
    counted = listings.offers(spark, sf).groupBy("category").agg(F.countDistinct("listing_id").alias("listings"), F.approx_count_distinct("listing_id", 0.02).alias("about"))
    return counted.select("category", "listings", (F.abs(F.col("about") - F.col("listings")) <= F.greatest(F.lit(1.0), F.col("listings") * 0.1)).alias("within"))


@query("SELECT l_shipmode_free, flag, n FROM (SELECT l_linestatus AS l_shipmode_free, coalesce(sum(CASE WHEN l_returnflag = 'A' THEN 1 END), 0)::BIGINT AS a, coalesce(sum(CASE WHEN l_returnflag = 'N' THEN 1 END), 0)::BIGINT AS nn, coalesce(sum(CASE WHEN l_returnflag = 'R' THEN 1 END), 0)::BIGINT AS r FROM lineitem GROUP BY 1) UNPIVOT (n FOR flag IN (a, nn, r))")
def pivot_flags(spark: SparkSession, sf: str) -> DataFrame:
    p = load(spark, sf, "lineitem", "l_linestatus", "l_returnflag").groupBy(F.col("l_linestatus").alias("l_shipmode_free")).pivot("l_returnflag", ["A", "N", "R"]).count().na.fill(0)
    return p.select("l_shipmode_free", F.col("A").alias("a"), F.col("N").alias("nn"), F.col("R").alias("r")).unpivot("l_shipmode_free", ["a", "nn", "r"], "flag", "n")


@query("SELECT l_returnflag, quantile_disc(l_quantity, 0.5) AS median_quantity, arg_max(l_orderkey * 10 + l_linenumber, l_orderkey * 10 + l_linenumber) AS last_line FROM lineitem GROUP BY 1")
def flag_percentiles(spark: SparkSession, sf: str) -> DataFrame:
    li = load(spark, sf, "lineitem", "l_returnflag", "l_quantity", "l_orderkey", "l_linenumber")
    k = F.col("l_orderkey") * 10 + F.col("l_linenumber")
    return li.groupBy("l_returnflag").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY l_quantity)").alias("median_quantity"), F.max_by(k, k).alias("last_line"))


@query("SELECT p_type, p_partkey, p_retailprice, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) QUALIFY rn <= 5")
def topk_per_leaf(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("p_type").orderBy(F.desc("p_retailprice"), "p_partkey")
    p = load(spark, sf, "part", "p_type", "p_partkey", "p_retailprice")
    return p.withColumns({"rn": F.row_number().over(w), "rk": F.rank().over(w), "dr": F.dense_rank().over(w)}).filter("rn <= 5")


@query("SELECT p_partkey, ntile(4) OVER w AS quartile, percent_rank() OVER w AS pr FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_retailprice, p_partkey)")
def price_quartiles(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("p_type").orderBy("p_retailprice", "p_partkey")
    return load(spark, sf, "part", "p_partkey", "p_type", "p_retailprice").select("p_partkey", F.ntile(4).over(w).alias("quartile"), F.percent_rank().over(w).alias("pr"))


@query("""WITH m AS (SELECT date_trunc('month', o_orderdate) AS month, count(*) AS n FROM orders GROUP BY 1)
SELECT strftime(month, '%Y-%m') AS month, n, sum(n) OVER (ORDER BY month)::BIGINT AS total, n - lag(n) OVER (ORDER BY month) AS more, lead(n) OVER (ORDER BY month) AS next_n,
sum(n) OVER (ORDER BY month ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS last_three FROM m""")
def running_listing_growth(spark: SparkSession, sf: str) -> DataFrame:
    m = load(spark, sf, "orders", "o_orderdate").groupBy(F.date_trunc("month", "o_orderdate").alias("m")).agg(F.count("*").alias("n"))
    w = Window.orderBy("m")  # a row a month
    return m.select(F.date_format("m", "yyyy-MM").alias("month"), "n", F.sum("n").over(w).alias("total"), (F.col("n") - F.lag("n").over(w)).alias("more"), F.lead("n").over(w).alias("next_n"), F.sum("n").over(w.rowsBetween(-2, 0)).alias("last_three"))


@query("SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS k_sum, count(*) AS n, min(props->>'k') AS k_min FROM events GROUP BY event_type")
def json_props(spark: SparkSession, sf: str) -> DataFrame:
    e = load(spark, sf, "events", "event_type", "props").select("event_type", F.from_json("props", "k long")["k"].alias("k"), F.get_json_object("props", "$.k").alias("ks"))
    return e.groupBy("event_type").agg(F.sum("k").alias("k_sum"), F.count("*").alias("n"), F.min("ks").alias("k_min"))


@query("SELECT doc_id, quality, toxic FROM labels UNION ALL SELECT doc_id, quality, toxic FROM labels UNION ALL SELECT doc_id, quality, toxic FROM labels")
def format_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """Labels written and read again as CSV, JSON and ORC."""
    from ..sources.formats import round_trip

    df = load(spark, sf, "labels")
    out = [round_trip(df, kind) for kind in ("csv", "json", "orc")]
    return out[0].unionByName(out[1]).unionByName(out[2])


@query("SELECT lang, source FROM documents WHERE n_chars > 3000 INTERSECT SELECT lang, source FROM documents WHERE n_chars < 500 EXCEPT SELECT lang, source FROM documents WHERE doc_id % 97 = 0")
def set_operations(spark: SparkSession, sf: str) -> DataFrame:
    d = load(spark, sf, "documents", "doc_id", "lang", "source", "n_chars")
    part = lambda c: d.filter(c).select("lang", "source")
    return part("n_chars > 3000").intersect(part("n_chars < 500")).exceptAll(part("doc_id % 97 = 0").distinct())
