"""Pairs, baselines, measures, verdicts and consolidation."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import text as tx
from ..operators import baselines, consolidate, metrics, pairs
from ..operators.store import Store
from ..sources import listings
from ..sources.formats import scratch, written
from ..sources.tables import load
from ..streaming import windows
from . import sql
from .registry import query
from .search import ASKED, LIST_PROBES, document_candidates, document_candidates_sql, offer_candidates, offer_candidates_sql, text_index, text_vectors

CUT = 800
O3 = sql.OFFERS3


def offers3(spark: SparkSession, sf: str) -> DataFrame:
    return written(listings.offers3(spark, sf))


_SPLIT = f"CASE WHEN ('0x' || substr(md5(product_key::VARCHAR), 1, 8))::BIGINT % {pairs.TEST_EVERY} = 0 THEN 'test' ELSE 'train' END"


def _negatives(keys: tuple[str, ...], origin: str) -> str:
    return f"SELECT a, b, false AS is_match, '{origin}' AS origin, split FROM (SELECT *, lead(a) OVER (PARTITION BY {', '.join(keys)}, split ORDER BY a) AS b FROM firsts) WHERE b IS NOT NULL"


LABELLED = f"""{O3},
firsts AS (SELECT product_key, category, p_name, p_brand, p_type, {_SPLIT} AS split, min(listing_id) AS a FROM offers3 GROUP BY ALL),
labelled AS (SELECT x.listing_id AS a, y.listing_id AS b, true AS is_match, 'same product' AS origin, {_SPLIT.replace('product_key', 'x.product_key')} AS split FROM offers3 x JOIN offers3 y ON x.product_key = y.product_key AND x.listing_id < y.listing_id
    UNION ALL {" UNION ALL ".join(_negatives(k, n) for k, n in pairs.NEGATIVES)})"""

SCORED = f"""{LABELLED}, {sql.dense('offers3', 'listing_id', 'title')},
scored AS (SELECT l.a, l.b, l.is_match, l.origin, l.split, coalesce(floor(1000 * list_dot_product(va.v, vb.v) / sqrt((x.n2 * y.n2)::DOUBLE)), 0)::BIGINT AS pm
    FROM labelled l LEFT JOIN feats_vec va ON va.listing_id = l.a LEFT JOIN feats_vec vb ON vb.listing_id = l.b LEFT JOIN feats_norm x ON x.listing_id = l.a LEFT JOIN feats_norm y ON y.listing_id = l.b)"""


def scored(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    o = offers3(spark, sf)
    return o, pairs.with_scores(pairs.labelled(o), o).drop("dot")


@query(f"WITH {sql.OFFERS} SELECT listing_id, product_key, min(listing_id) OVER w AS rep, count(*) OVER w - 1 AS n_links FROM offers WINDOW w AS (PARTITION BY product_key)")
def true_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """The truth about all listings: each with its product's smallest listing and the number of its true pairs."""
    return listings.true_classes(listings.offers(spark, sf))


@query(f"WITH {LABELLED} SELECT * FROM labelled")
def labelled_pair_sample(spark: SparkSession, sf: str) -> DataFrame:
    return pairs.labelled(offers3(spark, sf))


def _report(source: str, verdict: str, by: str = "") -> str:
    comma = by + "," if by else ""
    return f"""conf AS (SELECT {comma} count(*) FILTER (is_match AND {verdict}) AS tp, count(*) FILTER (NOT is_match AND {verdict}) AS fp, count(*) FILTER (is_match AND NOT {verdict}) AS fn, count(*) FILTER (NOT is_match AND NOT {verdict}) AS tn FROM {source} {'GROUP BY ' + by if by else ''}),
report AS (SELECT {comma} 'match' AS class, tp AS hits, fp AS false_alarms, fn AS misses FROM conf UNION ALL SELECT {comma} 'not_match', tn, fn, fp FROM conf),
rated AS (SELECT *, CASE WHEN hits + false_alarms > 0 THEN hits::DOUBLE / (hits + false_alarms) END AS precision, CASE WHEN hits + misses > 0 THEN hits::DOUBLE / (hits + misses) END AS recall,
    CASE WHEN 2 * hits + false_alarms + misses > 0 THEN (2 * hits)::DOUBLE / (2 * hits + false_alarms + misses) END AS f1 FROM report)"""


@query(f"WITH {SCORED} SELECT a, b, is_match, pm, pm >= {CUT} AS verdict FROM scored")
def distance_threshold(spark: SparkSession, sf: str) -> DataFrame:
    """One cut on the cosine for the whole catalogue."""
    return scored(spark, sf)[1].select("a", "b", "is_match", "pm", (F.col("pm") >= CUT).alias("verdict"))


@query(f"WITH {SCORED}, {_report('scored', f'(pm >= {CUT})')} SELECT * FROM rated")
def class_report(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.class_report(scored(spark, sf)[1].withColumn("verdict", F.col("pm") >= CUT), "is_match", "verdict")


@query(f"WITH {SCORED}, {_report('scored', f'(pm >= {CUT})', 'split')} SELECT split, (max(f1) FILTER (class = 'match') + max(f1) FILTER (class = 'not_match')) / 2 AS macro_f1 FROM rated GROUP BY split")
def macro_f1(spark: SparkSession, sf: str) -> DataFrame:
    r = metrics.class_report(scored(spark, sf)[1].withColumn("verdict", F.col("pm") >= CUT), "is_match", "verdict", "split")
    return r.groupBy("split").agg(((F.max(F.when(F.col("class") == "match", F.col("f1"))) + F.max(F.when(F.col("class") == "not_match", F.col("f1")))) / 2).alias("macro_f1"))


@query(f"""WITH {SCORED}, cuts AS (SELECT pm AS cut, sum(is_match::BIGINT)::BIGINT AS p, count(*) AS n FROM scored GROUP BY pm),
s AS (SELECT cut, sum(p) OVER (ORDER BY cut DESC)::BIGINT AS tp, sum(n) OVER (ORDER BY cut DESC)::BIGINT AS upto, sum(p) OVER ()::BIGINT AS all_p FROM cuts)
SELECT cut, tp, upto - tp AS fp, all_p - tp AS fn, tp::DOUBLE / upto AS precision, CASE WHEN all_p > 0 THEN tp::DOUBLE / all_p END AS recall, CASE WHEN tp + upto + all_p > 0 THEN (2 * tp)::DOUBLE / (upto + all_p) END AS f1 FROM s""")
def threshold_sweep(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.sweep(scored(spark, sf)[1], "pm", "is_match")


@query(f"""WITH {SCORED}, leaf AS (SELECT s.*, p_type FROM scored s JOIN offers3 o ON o.listing_id = a), cuts AS (SELECT p_type, pm AS cut, sum(is_match::BIGINT)::BIGINT AS p, count(*) AS n FROM leaf GROUP BY ALL),
s AS (SELECT *, sum(p) OVER w::BIGINT AS tp, sum(n) OVER w::BIGINT AS upto, sum(p) OVER (PARTITION BY p_type)::BIGINT AS all_p FROM cuts WINDOW w AS (PARTITION BY p_type ORDER BY cut DESC))
SELECT p_type, cut, tp, upto - tp AS fp, all_p - tp AS fn FROM s QUALIFY row_number() OVER (PARTITION BY p_type ORDER BY (2 * tp)::DOUBLE / (upto + all_p) DESC, cut DESC) = 1""")
def category_thresholds(spark: SparkSession, sf: str) -> DataFrame:
    """The best cut of each top category."""
    o, s = scored(spark, sf)
    leaf = s.join(o.select(F.col("listing_id").alias("a"), "p_type"), "a")
    return baselines.category_thresholds(leaf, "p_type", "pm", "is_match")


@query(f"""WITH {SCORED}, sides AS (SELECT s.*, x.p_size AS sa, y.p_size AS sb, x.price AS pa, y.price AS pb, len(list_intersect(list_distinct(regexp_extract_all(lower(x.title), '[\\p{{L}}\\p{{N}}]+')), list_distinct(regexp_extract_all(lower(y.title), '[\\p{{L}}\\p{{N}}]+')))) AS shared
    FROM scored s JOIN offers3 x ON x.listing_id = a JOIN offers3 y ON y.listing_id = b), {_report('sides', '(sa = sb AND shared >= 2 AND pa <= 2 * pb AND pb <= 2 * pa)')} SELECT * FROM rated""")
def rule_report(spark: SparkSession, sf: str) -> DataFrame:
    """Size, token and price rules as a matcher."""
    o, s = scored(spark, sf)
    side = lambda k: o.select(F.col("listing_id").alias(k), F.col("p_size").alias(f"s{k}"), F.col("price").alias(f"p{k}"), F.array_distinct(tx.tokens(F.col("title"))).alias(f"t{k}"))
    j = s.join(side("a"), "a").join(side("b"), "b")
    verdict = baselines.rule_verdict(F.col("sa"), F.col("sb"), F.col("pa"), F.col("pb"), F.size(F.array_intersect("ta", "tb")))
    return metrics.class_report(j.withColumn("verdict", verdict), "is_match", "verdict")


def _blocks(keyed: str) -> str:
    return f"keyed AS ({keyed}), blocks AS (SELECT k, min(id) OVER w AS rep, id FROM keyed WINDOW w AS (PARTITION BY k) QUALIFY count(*) OVER w > 1)"


_TITLE_KEY = r"trim(regexp_replace(lower(title), '[^\p{L}\p{N}]+', ' ', 'g'))"
_TOKEN_KEY = r"array_to_string(list_sort(list_distinct(regexp_extract_all(lower(title), '[\p{L}\p{N}]+'))), ' ')"


@query(f"WITH {sql.OFFERS}, {_blocks(f'SELECT listing_id AS id, {_TITLE_KEY} AS k FROM offers')} SELECT rep AS a, id AS b FROM blocks WHERE rep <> id")
def keyword_exact(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.keyword_exact(listings.offers(spark, sf), "listing_id", "title")


@query(f"WITH {sql.OFFERS}, {_blocks(f'SELECT listing_id AS id, {_TOKEN_KEY} AS k FROM offers')} SELECT rep AS a, id AS b FROM blocks WHERE rep <> id")
def keyword_all_tokens(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.keyword_all_tokens(listings.offers(spark, sf), "listing_id", "title")


@query(rf"""WITH t AS (SELECT doc_id AS id, tok, count(*) AS tf FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\p{{L}}\p{{N}}]+')) AS tok FROM documents) GROUP BY ALL),
st AS (SELECT id, sum(tf)::BIGINT AS len FROM t GROUP BY id), g AS (SELECT count(*) AS n, sum(len)::DOUBLE / count(*) AS mean FROM st),
idf AS (SELECT tok, mean, floor(1000 * ln(1 + (n - df + 0.5::DOUBLE) / (df + 0.5::DOUBLE))) AS idf FROM (SELECT tok, count(*) AS df FROM t GROUP BY tok), g),
w AS (SELECT tok, id, floor(idf * tf * ({baselines.K1}::DOUBLE + 1) / (tf + {baselines.K1}::DOUBLE * (1 - {baselines.B}::DOUBLE + {baselines.B}::DOUBLE * len / mean)))::BIGINT AS w FROM t JOIN idf USING (tok) JOIN st USING (id))
SELECT q.id AS q, c.id AS c, sum(c.w)::BIGINT AS score, row_number() OVER (PARTITION BY q.id ORDER BY sum(c.w) DESC, c.id)::INT AS rank FROM w c JOIN w q ON c.tok = q.tok AND c.id <> q.id WHERE q.id % 20 = 0 GROUP BY q.id, c.id QUALIFY rank <= 5""")
def keyword_bm25(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.keyword_bm25(load(spark, sf, "documents", "doc_id", "text"), "doc_id", "text", 5)


def _bands(relation: str, key: str, text: str) -> str:
    mins = ", ".join(f"min((h * {a} + {b}) % {baselines.PRIME}) AS m{s}" for s in range(baselines.BANDS * baselines.ROWS) for a, b in [baselines.permutation(s)])
    keys = " UNION ALL ".join(f"SELECT id, '{b}|' || m{2 * b} || '|' || m{2 * b + 1} AS k FROM mins" for b in range(baselines.BANDS))
    return rf"toks AS (SELECT {key} AS id, unnest(regexp_extract_all(lower({text}), '[\p{{L}}\p{{N}}]+')) AS tok FROM {relation}), mins AS (SELECT id, {mins} FROM (SELECT id, ('0x' || substr(md5(tok), 1, 8))::BIGINT AS h FROM toks) GROUP BY id), {_blocks(keys)}"


@query(f"WITH {_bands('documents', 'doc_id', 'text')} SELECT k, rep, id FROM blocks")
def lsh_candidates(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.lsh_candidates(load(spark, sf, "documents", "doc_id", "text"), "doc_id", "text")


_BLACK = f"""{_bands('offers3', 'listing_id', 'title')}, shared AS (SELECT DISTINCT s.a, s.b FROM scored s JOIN keyed x ON x.id = s.a JOIN keyed y ON y.id = s.b AND x.k = y.k),
black AS (SELECT a, b FROM shared JOIN offers3 x ON x.listing_id = a JOIN offers3 y ON y.listing_id = b WHERE x.p_brand = y.p_brand AND x.price * 0.8::DOUBLE <= y.price AND x.price * 1.25::DOUBLE >= y.price),
judged AS (SELECT s.*, EXISTS (SELECT 1 FROM black k WHERE k.a = s.a AND k.b = s.b) AS flagged FROM scored s)"""


@query(f"WITH {SCORED}, {_BLACK}, {_report('judged', 'flagged')} SELECT * FROM rated")
def black_box_report(spark: SparkSession, sf: str) -> DataFrame:
    """The stand-in for an outside service, which gives verdicts without scores."""
    o, s = scored(spark, sf)
    return metrics.class_report(baselines.black_box(s, o), "is_match", "flagged")


#: Score from which the matcher flags a pair for the biased test set.
FLAGGED = 700


@query(f"WITH {SCORED}, {_BLACK} SELECT DISTINCT a, b, is_match, pm >= {FLAGGED} AS by_score, flagged AS by_service FROM judged WHERE pm >= {FLAGGED} OR flagged")
def biased_test_set(spark: SparkSession, sf: str) -> DataFrame:
    """Labelled pairs that either system flags: a test set biased by how it was chosen."""
    o, s = scored(spark, sf)
    j = baselines.black_box(s, o).withColumn("by_score", F.col("pm") >= FLAGGED)
    return j.filter("by_score OR flagged").select("a", "b", "is_match", "by_score", F.col("flagged").alias("by_service")).distinct()


@query(f"WITH {SCORED}, v AS (SELECT origin, split, pm >= {CUT} AS verdict FROM scored) SELECT origin, split, verdict, count(*) AS n, grouping_id(origin, split, verdict)::BIGINT AS g FROM v GROUP BY CUBE (origin, split, verdict)")
def match_cube(spark: SparkSession, sf: str) -> DataFrame:
    v = scored(spark, sf)[1].withColumn("verdict", F.col("pm") >= CUT)
    return v.cube("origin", "split", "verdict").agg(F.count("*").alias("n"), F.grouping_id("origin", "split", "verdict").alias("g"))


@query(f"""WITH {O3}, one AS (SELECT product_key, p_name, p_brand, p_type, any_value(p_size) AS p_size, min(listing_id) AS id FROM offers3 GROUP BY ALL), v AS (SELECT x.id AS a, y.id AS b, CASE WHEN x.p_size = y.p_size THEN 'none' ELSE 'size' END AS differs FROM one x JOIN one y USING (p_name, p_brand, p_type) WHERE x.id < y.id),
{sql.features('offers3', 'listing_id', 'title')}, d AS (SELECT a, b, differs, sum(x.val * y.val)::BIGINT AS dot FROM v JOIN feats x ON x.listing_id = a JOIN feats y ON y.listing_id = b AND x.dim = y.dim GROUP BY ALL)
SELECT differs, count(*) AS n, count(*) FILTER (floor(1000 * coalesce(dot, 0) / sqrt((x.n2 * y.n2)::DOUBLE)) >= {CUT}) AS false_matches FROM v LEFT JOIN d USING (a, b, differs) JOIN feats_norm x ON x.listing_id = a JOIN feats_norm y ON y.listing_id = b GROUP BY differs""")
def error_slices(spark: SparkSession, sf: str) -> DataFrame:
    """False matches among variants of one name, brand and type, by what differs."""
    o = offers3(spark, sf)
    v = pairs.with_scores(listings.variant_pairs(o), o)
    return v.groupBy("differs").agg(F.count("*").alias("n"), F.count_if(F.col("pm") >= CUT).alias("false_matches"))


@query(f"""WITH {O3}, {sql.features('offers3', 'listing_id', 'title')}, s AS (SELECT p_type, dim, sum(val)::BIGINT AS s FROM feats JOIN offers3 USING (listing_id) GROUP BY ALL),
sq AS (SELECT p_type, sum(s * s)::BIGINT AS sum_sq FROM s GROUP BY p_type), n AS (SELECT p_type, count(*) AS n, sum(n2)::BIGINT AS own_sq FROM feats_norm JOIN offers3 USING (listing_id) GROUP BY p_type)
SELECT p_type, n, own_sq, sum_sq, (sum_sq - own_sq)::DOUBLE / (n * (n - 1)) AS mean_dot FROM sq JOIN n USING (p_type)""")
def leaf_collapse(spark: SparkSession, sf: str) -> DataFrame:
    """Mean inner product within a category from sums of vectors: no pairs are formed."""
    o = offers3(spark, sf)
    f = tx.hashed_features(o.select("listing_id", "title"), "listing_id", "title").join(o.select("listing_id", "p_type"), "listing_id")
    sums = f.groupBy("p_type", "dim").agg(F.sum("val").alias("s")).groupBy("p_type").agg(F.sum(F.col("s") * F.col("s")).alias("sum_sq"))
    own = f.groupBy("p_type").agg(F.countDistinct("listing_id").alias("n"), F.sum(F.col("val") * F.col("val")).alias("own_sq"))
    return own.join(sums, "p_type").select("p_type", "n", "own_sq", "sum_sq", ((F.col("sum_sq") - F.col("own_sq")) / (F.col("n") * (F.col("n") - 1))).alias("mean_dot"))


@query(f"WITH {offer_candidates_sql(5)} SELECT listing_id FROM offers WHERE listing_id IN (SELECT q FROM candidates UNION SELECT c FROM candidates)")
def lazy_image_ids(spark: SparkSession, sf: str) -> DataFrame:
    """Listings whose images have to be encoded for a query set: those in candidate pairs, by a semi-join."""
    o = written(listings.offers(spark, sf))
    ids = offer_candidates(o, 5).select(F.explode(F.array("q", "c")).alias("listing_id"))
    return o.select("listing_id").join(ids, "listing_id", "left_semi")


_SHINGLES = r"""ws AS (SELECT doc_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS w FROM documents),
every_sh AS (SELECT DISTINCT doc_id, array_to_string(w[i:i+2], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM ws)),
same AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY k) AS rep FROM (SELECT doc_id, md5(string_agg(s, chr(10) ORDER BY s)) AS k FROM every_sh GROUP BY doc_id)),
sh AS (SELECT e.* FROM every_sh e JOIN same USING (doc_id) WHERE doc_id = rep), sz AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY 1),
inter AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS i FROM sh x JOIN sh y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY ALL),
near AS (SELECT a, b, i::DOUBLE / (x.n + y.n - i) AS jaccard FROM inter JOIN sz x ON x.doc_id = a JOIN sz y ON y.doc_id = b WHERE 2 * i >= x.n + y.n - i
    UNION ALL SELECT rep, doc_id, 1.0::DOUBLE FROM same WHERE doc_id <> rep)"""


def near_copies(spark: SparkSession, sf: str) -> DataFrame:
    """a, b, jaccard: exact Jaccard of word 3-shingles of at least one half between texts with different shingle sets, each set
    standing for the text with the smallest id, and each other text linked to the one that stands for it (1.0). So k copies make k
    rows. Only the rarest half of a set's shingles is indexed: sets that share half of their union share one of those, and frequent
    shingles meet no one."""
    d = load(spark, sf, "documents", "doc_id", "text").withColumn("w", tx.tokens(F.col("text"))).filter(F.size("w") >= 3)
    made = F.array_sort(F.array_distinct(F.transform(F.sequence(F.lit(0), F.size("w") - 3), lambda i: F.xxhash64(F.concat_ws(" ", F.get("w", i), F.get("w", i + 1), F.get("w", i + 2))))))
    every = written(d.select("doc_id", made.alias("s")).withColumn("k", F.md5(F.array_join(F.transform("s", lambda x: x.cast("string")), ","))))
    same = written(every.select("doc_id", "k").join(every.groupBy("k").agg(F.min("doc_id").alias("rep")), "k").select("doc_id", "rep"))
    sets = written(every.join(same.filter("doc_id = rep"), "doc_id", "left_semi").select("doc_id", "s", F.size("s").alias("n")))
    each = sets.select("doc_id", "n", F.explode("s").alias("h"))
    ranked = each.join(each.groupBy("h").agg(F.count("*").alias("df")).filter("df > 1"), "h", "left")
    # Shingles in one text alone (df null) come first: they take up prefix places and join nothing.
    prefix = ranked.groupBy("doc_id", "n").agg(F.sort_array(F.collect_list(F.struct(F.coalesce("df", F.lit(1)).alias("df"), "h"))).alias("o"))
    keep = F.slice("o", F.lit(1), F.size("o") - F.ceil(F.size("o") / 2).cast("int") + 1)
    index = prefix.select("doc_id", "n", F.explode(keep).alias("x")).filter("x.df > 1").select("doc_id", "n", F.col("x.h").alias("h"))
    side = lambda k: index.select("h", F.col("doc_id").alias(k), F.col("n").alias(f"n{k}"))
    # A Jaccard of one half needs sizes within a factor of two.
    near = side("a").join(side("b"), "h").filter("a < b AND na <= 2 * nb AND nb <= 2 * na").select("a", "b").distinct()
    side = lambda k: sets.select(F.col("doc_id").alias(k), F.col("s").alias(f"s{k}"))
    j = near.join(side("a"), "a").join(side("b"), "b").withColumn("i", F.size(F.array_intersect("sa", "sb")))
    whole = F.size("sa") + F.size("sb") - F.col("i")
    pairs = j.filter(2 * F.col("i") >= whole).select("a", "b", (F.col("i") / whole).alias("jaccard"))
    return pairs.unionByName(same.filter("doc_id != rep").select(F.col("rep").alias("a"), F.col("doc_id").alias("b"), F.lit(1.0).alias("jaccard")))


@query(f"WITH {_SHINGLES} SELECT a, b, jaccard FROM near")
def jaccard_near_copies(spark: SparkSession, sf: str) -> DataFrame:
    return near_copies(spark, sf)


@query(f"WITH {_SHINGLES}, {document_candidates_sql(10, 'true')} SELECT count(*) AS pairs, count(*) FILTER (EXISTS (SELECT 1 FROM candidates WHERE q = a AND c = b) OR EXISTS (SELECT 1 FROM candidates WHERE q = b AND c = a)) AS found FROM near")
def near_copy_candidate_recall(spark: SparkSession, sf: str) -> DataFrame:
    """Near copies of which one is among the other's top 10 by hashed features."""
    hits = document_candidates(spark, sf, 10, everyone=True).select(F.least("q", "c").alias("a"), F.greatest("q", "c").alias("b")).distinct().withColumn("hit", F.lit(1))
    return near_copies(spark, sf).join(hits, ["a", "b"], "left").agg(F.count("*").alias("pairs"), F.count("hit").alias("found"))


@query(f"WITH RECURSIVE {_SHINGLES}, e AS (SELECT a AS u, b AS v FROM near UNION SELECT b, a FROM near), r(id, g) AS (SELECT u, u FROM e UNION SELECT e.v, r.g FROM r JOIN e ON e.u = r.id) SELECT id, min(g) AS group_id FROM r GROUP BY id")
def duplicate_groups(spark: SparkSession, sf: str) -> DataFrame:
    return consolidate.groups(near_copies(spark, sf))


@query(f"WITH {sql.OFFERS} SELECT product_key, listing_id, price, n_offers FROM (SELECT *, count(*) OVER (PARTITION BY product_key) AS n_offers FROM offers JOIN supplier ON seller = s_suppkey QUALIFY row_number() OVER (PARTITION BY product_key ORDER BY price, s_acctbal DESC, listing_id) = 1)")
def buy_box(spark: SparkSession, sf: str) -> DataFrame:
    return consolidate.buy_box(listings.offers(spark, sf), load(spark, sf, "supplier", "s_suppkey", "s_acctbal"))


@query("""SELECT doc_id AS id, CASE WHEN doc_id % 3 = 0 THEN 2 ELSE 1 END::BIGINT AS version, CASE WHEN doc_id % 3 = 0 THEN upper(source) ELSE source END AS source FROM documents WHERE (doc_id % 2 = 0 OR doc_id % 3 = 0) AND doc_id % 10 <> 0""")
def store_upsert_state(spark: SparkSession, sf: str) -> DataFrame:
    """Insert even ids, change or add multiples of 3 (twice: a replay), delete multiples of 10, compact."""
    d = load(spark, sf, "documents", "doc_id", "source").withColumnRenamed("doc_id", "id")
    s = Store(spark, scratch(spark), "source string")
    s.upsert(d.filter("id % 2 = 0").withColumn("version", F.lit(1).cast("long")), 1)
    for _ in range(2):
        s.upsert(d.filter("id % 3 = 0").select("id", F.lit(2).cast("long").alias("version"), F.upper("source").alias("source")), 2)
    s.delete(d.filter("id % 10 = 0").select("id"), 3, 3)
    s.compact(3)
    return s.read()


#: Frozen decider: hidden unit k weighs |a - b| by -(1 + (k + dim) % 3) and a * b by 4 + k; output weights and bias. Fixed by rule.
HIDDEN, OUT, BIAS = 4, (3, 2, 2, 1), -40
_Z = " + ".join(f"{OUT[k]} * greatest(0, sum(- (1 + ({k} + dim) % 3) * abs(va - vb) + {4 + k} * va * vb))" for k in range(HIDDEN))
_FROZEN = f"""{{pairs}}, dims AS (SELECT unnest(range(128)) AS dim),
z AS (SELECT a, b, any_value(is_match) AS is_match, ({_Z} + {BIAS})::BIGINT AS z FROM (SELECT p.a, p.b, p.is_match, dims.dim AS dim, coalesce(x.val, 0) AS va, coalesce(y.val, 0) AS vb FROM wanted p CROSS JOIN dims
    LEFT JOIN feats x ON x.listing_id = p.a AND x.dim = dims.dim LEFT JOIN feats y ON y.listing_id = p.b AND y.dim = dims.dim) GROUP BY a, b)"""


def titles(o: DataFrame, k: str, *also: str) -> DataFrame:
    """The listings' ids as ``k``, and title{k} and other columns under such names."""
    return o.select(F.col("listing_id").alias(k), *[F.col(c).alias(f"{c}{k}") for c in ("title", *also)])


def frozen_scores(wanted: DataFrame, o: DataFrame) -> DataFrame:
    """Adds z, the frozen decider's output for both text vectors; z >= 0 is a match. Titles (titlea, titleb) that pairs don't bring come
    from ``o``; vectors are made where pairs are scored, so none travels."""
    kept, j = [c for c in wanted.columns if c not in ("titlea", "titleb")], wanted
    for k in "ab":
        if f"title{k}" not in j.columns:
            j = j.join(titles(o, k), k)
    j = j.select(*kept, *[tx.first_tokens(F.col(f"title{k}")).alias(f"title{k}") for k in "ab"])

    def score(batches):
        import numpy as np
        import pyarrow as pa

        count, dims = tx.token_counter(tx.WIDTH), np.arange(tx.WIDTH)
        far = np.array([1 + (k + dims) % 3 for k in range(HIDDEN)], float).T
        for b in batches:
            for i in range(0, b.num_rows, 4096):
                part = b.slice(i, 4096)
                va, vb = (count(part.column(len(kept) + k)) for k in (0, 1))
                units = np.outer((va * vb).sum(1), 4 + np.arange(HIDDEN)) - np.abs(va - vb) @ far  # whole numbers, exact
                z = (np.maximum(units, 0) @ np.array(OUT, float) + BIAS).astype(np.int64)
                yield pa.RecordBatch.from_arrays([*part.columns[: len(kept)], pa.array(z)], names=[*kept, "z"])

    return j.mapInArrow(score, T.StructType([*wanted.select(*kept).schema.fields, T.StructField("z", T.LongType())]))


@query(f"WITH {_FROZEN.format(pairs=LABELLED + ', ' + sql.features('offers3', 'listing_id', 'title') + ', wanted AS (SELECT DISTINCT a, b, is_match FROM labelled)')} SELECT a, b, is_match, z, z >= 0 AS verdict FROM z")
def decider_score_frozen(spark: SparkSession, sf: str) -> DataFrame:
    o = offers3(spark, sf)
    return frozen_scores(pairs.labelled(o).select("a", "b", "is_match").distinct(), o).select("a", "b", "is_match", "z", (F.col("z") >= 0).alias("verdict"))


def candidate_pairs(o: DataFrame, top: int = 5) -> DataFrame:
    """a < b, is_match and both titles: the candidate pairs of a query set, once each."""
    c = offer_candidates(o, top).select(F.least("q", "c").alias("a"), F.greatest("q", "c").alias("b")).distinct()
    j = c.join(titles(o, "a", "product_key"), "a").join(titles(o, "b", "product_key"), "b")
    return j.select("a", "b", (F.col("product_keya") == F.col("product_keyb")).alias("is_match"), "titlea", "titleb")


@query(f"""WITH {offer_candidates_sql(5)}, wanted AS (SELECT DISTINCT least(q, c) AS a, greatest(q, c) AS b, x.product_key = y.product_key AS is_match FROM candidates JOIN offers x ON x.listing_id = q JOIN offers y ON y.listing_id = c),
{_FROZEN.format(pairs='one_more AS (SELECT 1)')} SELECT a, b, is_match, z FROM z WHERE z >= 0""")
def match_pipeline(spark: SparkSession, sf: str) -> DataFrame:
    """Listings to verdicts over the whole catalogue: a query set's top 5 by title through stored inverted lists, pairs once each,
    frozen decider, matches only. ``match_report`` has the trained decider on text and images."""
    o = written(listings.offers(spark, sf).select("listing_id", "product_key", "title"))
    return frozen_scores(candidate_pairs(o), o).filter("z >= 0").select("a", "b", "is_match", "z")


@query(rf"""WITH {sql.OFFERS}, g AS (SELECT listing_id, unnest(list_transform(range(1, len(t) - 1), lambda i: substr(t, i, 3))) AS g FROM (SELECT listing_id, {_TITLE_KEY} AS t FROM offers) WHERE len(t) >= 3),
h AS (SELECT listing_id, ('0x' || substr(md5(g), 1, 8))::BIGINT AS h FROM g), f AS (SELECT listing_id, h % {tx.GENERIC_WIDTH} AS dim, sum(CASE WHEN (h >> 16) % 2 = 1 THEN -1 ELSE 1 END)::BIGINT AS val FROM h GROUP BY ALL HAVING val <> 0)
SELECT listing_id, count(*) AS n_dims, sum(val * val)::BIGINT AS n2, sum(dim * val)::BIGINT AS moment FROM f GROUP BY 1""")
def generic_512(spark: SparkSession, sf: str) -> DataFrame:
    """Vectors of a general 512-d encoder that is not tuned to the catalogue, in digest: non-zero numbers, squared norm, first moment."""
    return tx.generic_digest(listings.offers(spark, sf), "listing_id", "title")


#: How two listings of one product are worded, from the bits that chose the wording: layout (h % 5), synonyms (bits 4, 5), brand (bit 6).
_WORDING = """CASE WHEN x.h % 5 <> y.h % 5 OR (x.h >> 6) % 2 <> (y.h >> 6) % 2 THEN 'otherwise' WHEN (x.h >> 4) % 4 <> (y.h >> 4) % 4 THEN 'by synonyms only' ELSE 'not at all' END"""


@query(rf"""WITH {SCORED}, keys AS (SELECT listing_id, {_TITLE_KEY} AS same_title, {_TOKEN_KEY} AS same_tokens FROM offers3)
SELECT {_WORDING} AS differ, count(*) AS pairs, count(*) FILTER (kx.same_title = ky.same_title) AS by_title, count(*) FILTER (kx.same_tokens = ky.same_tokens) AS by_tokens, count(*) FILTER (pm >= {FLAGGED}) AS by_vectors
FROM scored JOIN offers3 x ON x.listing_id = a JOIN offers3 y ON y.listing_id = b JOIN keys kx ON kx.listing_id = a JOIN keys ky ON ky.listing_id = b WHERE origin = 'same product' GROUP BY 1""")
def keyword_miss(spark: SparkSession, sf: str) -> DataFrame:
    """True pairs by how their titles differ, and how many of them equal titles, equal token sets and close vectors find: keywords miss
    pairs that differ by a synonym."""
    o, s = scored(spark, sf)
    side = lambda k: o.select(F.col("listing_id").alias(k), F.col("h").alias(f"h{k}"), tx.normalise(F.col("title")).alias(f"t{k}"), baselines.token_set(F.col("title")).alias(f"w{k}"))
    j = s.filter("origin = 'same product'").join(side("a"), "a").join(side("b"), "b")
    bits = lambda c, at, n: F.pmod(F.shiftright(c, at), F.lit(n))
    other = (F.col("ha") % 5 != F.col("hb") % 5) | (bits("ha", 6, 2) != bits("hb", 6, 2))
    differ = F.when(other, "otherwise").when(bits("ha", 4, 4) != bits("hb", 4, 4), "by synonyms only").otherwise("not at all")
    return j.groupBy(differ.alias("differ")).agg(F.count("*").alias("pairs"), F.count_if(F.col("ta") == F.col("tb")).alias("by_title"), F.count_if(F.col("wa") == F.col("wb")).alias("by_tokens"), F.count_if(F.col("pm") >= FLAGGED).alias("by_vectors"))


_EFFECT = "SELECT '{name}' AS grouping, count(*) AS listings, count(DISTINCT g) AS products, max(n) AS largest, sum((price > best)::BIGINT)::BIGINT AS dearer, count(DISTINCT CASE WHEN mixed THEN g END) AS impure FROM (SELECT *, count(*) OVER w AS n, min(price) OVER w AS best, min(product_key) OVER w <> max(product_key) OVER w AS mixed FROM ({rows}) WINDOW w AS (PARTITION BY g))"
_BY_TOKENS = f"SELECT *, min(listing_id) OVER (PARTITION BY {_TOKEN_KEY}) AS g FROM offers"


@query(f"WITH {sql.OFFERS} {_EFFECT.format(name='none', rows='SELECT *, listing_id AS g FROM offers')} UNION ALL {_EFFECT.format(name='equal tokens', rows=_BY_TOKENS)} UNION ALL {_EFFECT.format(name='truth', rows='SELECT *, product_key AS g FROM offers')}")
def consolidation(spark: SparkSession, sf: str) -> DataFrame:
    """What grouping does to the catalogue: products before and after, the largest group, listings that are dearer than their group's
    best price, and groups that hold more than one product. Without grouping, by equal token sets, and by the truth."""
    o = written(listings.offers(spark, sf))
    tokens = baselines.keyword_all_tokens(o, "listing_id", "title").select(F.col("b").alias("listing_id"), F.col("a").alias("rep"))
    by_tokens = o.join(tokens, "listing_id", "left").withColumn("g", F.coalesce("rep", "listing_id"))
    out = None
    for name, rows in (("none", o.withColumn("g", F.col("listing_id"))), ("equal tokens", by_tokens), ("truth", o.withColumn("g", F.col("product_key")))):
        r = consolidate.effect(rows).select(F.lit(name).alias("grouping"), "listings", "products", "largest", "dearer", "impure")
        out = r if out is None else out.unionByName(r)
    return out


@query(f"""WITH {offer_candidates_sql(5)}, wanted AS (SELECT q AS a, c AS b, x.product_key = y.product_key AS is_match FROM candidates JOIN offers x ON x.listing_id = q JOIN offers y ON y.listing_id = c),
{_FROZEN.format(pairs='one_more AS (SELECT 1)')} SELECT a, b, z FROM z WHERE z >= 0""")
def serving(spark: SparkSession, sf: str) -> DataFrame:
    """Daily serving: arriving listings come as a stream, each batch is searched in the stored index, scored by the frozen decider and
    written; a replayed batch overwrites itself. Batch by batch gives what one batch gives."""
    o = written(listings.offers(spark, sf).select("listing_id", "title"))
    _, index = text_index(o, "listing_id", "title")
    path = scratch(spark)
    o.filter(ASKED).select("listing_id", "title").repartition(3, "listing_id").write.parquet(f"{path}/arrivals")
    arrivals = spark.readStream.schema("listing_id long, title string").option("maxFilesPerTrigger", 1).parquet(f"{path}/arrivals")
    batches: list[str] = []

    def serve(batch: DataFrame, number: int) -> None:
        hits = index.search(text_vectors(batch, "listing_id", "title"), 5, LIST_PROBES, positive=True)
        found = hits.select(F.col("q").alias("a"), F.col("c").alias("b")).join(titles(batch, "a"), "a")
        scored_hits = frozen_scores(found, o).filter("z >= 0")
        scored_hits.select("a", "b", "z").write.mode("overwrite").parquet(f"{path}/matches/{number}")
        batches.append(f"{path}/matches/{number}")

    windows.collect_updates(arrivals, serve, "append")
    return spark.read.schema("a long, b long, z long").parquet(*batches)
