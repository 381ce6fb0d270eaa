"""Vectors, indexes and what they cost."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as tx
from ..functions import vectors as vx
from ..operators import flat, hnsw, ivf, metrics, pca, quantized
from ..sources import listings
from ..sources.formats import written
from ..sources.tables import load
from . import sql
from .registry import query

TOP = 10


#: Rows that ask in searches: every EVERY-th id.
EVERY = 20


def asked(v: DataFrame) -> DataFrame:
    return v.filter(F.col("id") % EVERY == 0)


def fixed(spark: SparkSession, sf: str) -> DataFrame:
    return vx.embeddings(load(spark, sf, "embeddings", "vec_id", "embedding"))


@query(f"WITH {sql.fixed()} SELECT id, list(val ORDER BY dim)::VARCHAR AS vec, any_value(n2)::BIGINT AS n2 FROM vecs JOIN norms USING (id) GROUP BY id")
def fixed_point_vectors(spark: SparkSession, sf: str) -> DataFrame:
    v = fixed(spark, sf)
    return v.select("id", F.concat(F.lit("["), F.array_join(F.transform("vec", lambda x: x.cast("string")), ", "), F.lit("]")).alias("vec"), vx.squared_norm(F.col("vec")).alias("n2"))


_PAIRS = "pairs AS (SELECT a.id AS q, b.id AS c, sum(a.val * b.val)::BIGINT AS dot FROM vecs a JOIN vecs b ON a.dim = b.dim AND a.id <> b.id WHERE a.id % 20 = 0 GROUP BY ALL)"
_EXACT = f"exact AS (SELECT q, c, dot / sqrt((a.n2 * b.n2)::DOUBLE) AS score, row_number() OVER (PARTITION BY q ORDER BY dot / sqrt((a.n2 * b.n2)::DOUBLE) DESC, c)::INT AS rank FROM pairs JOIN norms a ON q = a.id JOIN norms b ON c = b.id QUALIFY rank <= {TOP})"


@query(f"WITH {sql.fixed()}, {_PAIRS}, {_EXACT} SELECT q, c, score, rank FROM exact")
def flat_knn_cosine(spark: SparkSession, sf: str) -> DataFrame:
    """Exact neighbours of a query set: blocks of queries against blocks of all vectors."""
    v = fixed(spark, sf)
    return flat.search(asked(v), v, TOP)


@query(f"WITH {sql.fixed()}, {_PAIRS} SELECT q, c, -(a.n2 + b.n2 - 2 * dot)::DOUBLE AS score, row_number() OVER (PARTITION BY q ORDER BY a.n2 + b.n2 - 2 * dot, c)::INT AS rank FROM pairs JOIN norms a ON q = a.id JOIN norms b ON c = b.id QUALIFY rank <= {TOP}")
def flat_knn_l2(spark: SparkSession, sf: str) -> DataFrame:
    v = fixed(spark, sf)
    return flat.search(asked(v), v, TOP, metric="l2")


def text_vectors(df: DataFrame, key: str, text: str, width: int = tx.WIDTH) -> DataFrame:
    """id, vec (signed bytes) of texts that have one: hashed features of the first 32 tokens."""
    return tx.packed_features(df.select(key, text), key, text, width=width)


def text_index(df: DataFrame, key: str, text: str) -> tuple[DataFrame, ivf.Index]:
    """Text vectors and their stored inverted lists."""
    v = written(text_vectors(df, key, text))
    return v, ivf.Index.build(v, ivf.seeds(v, lists_for(v)))


#: Lists that are probed for each text.
LIST_PROBES = 4


def document_candidates_sql(top: int, who: str) -> str:
    return f"{sql.dense('documents', 'doc_id', 'text')}, {sql.text_lists('documents', 'doc_id', who, LIST_PROBES, top)}"


def document_candidates(spark: SparkSession, sf: str, top: int, everyone: bool = False) -> DataFrame:
    v, index = text_index(load(spark, sf, "documents", "doc_id", "text"), "doc_id", "text")
    return index.search(v if everyone else asked(v), top, LIST_PROBES, positive=True)


@query(f"WITH {document_candidates_sql(5, f'doc_id % {EVERY} = 0')} SELECT q, c, score, rank FROM candidates")
def text_topn_candidates(spark: SparkSession, sf: str) -> DataFrame:
    """Top 5 by hashed features of the first 32 tokens in the closest lists; the query's own text is left out."""
    return document_candidates(spark, sf, 5)


def lists_for(v: DataFrame) -> int:
    return max(1, math.isqrt(v.count()))


@query(f"WITH {sql.inverted(1)} SELECT id, list_id FROM member")
def ivf_assign(spark: SparkSession, sf: str) -> DataFrame:
    v = fixed(spark, sf)
    return ivf.assign(v, ivf.seeds(v, lists_for(v))).select("id", F.col("list_id").cast("long").alias("list_id"))


@query(f"WITH {sql.inverted(1)} SELECT list_id, dim, count(*) AS n, floor(sum(val) / count(*))::BIGINT AS val FROM member JOIN vecs USING (id) GROUP BY list_id, dim")
def ivf_lloyd_step(spark: SparkSession, sf: str) -> DataFrame:
    v = fixed(spark, sf)
    return ivf.lloyd_step(v, ivf.seeds(v, lists_for(v))).select(F.col("list_id").cast("long").alias("list_id"), F.col("dim").cast("long").alias("dim"), "n", "val")


@query(f"WITH {sql.inverted(1)}, s AS (SELECT list_id, count(*) AS n FROM member GROUP BY list_id) SELECT list_id, n, sum(n) OVER ()::BIGINT AS total, max(n) OVER () * 1000 // (sum(n) OVER () // count(*) OVER ())::BIGINT AS skew FROM s")
def ivf_lists(spark: SparkSession, sf: str) -> DataFrame:
    """Sizes of the lists; skew: the largest against the mean, per mille."""
    from pyspark.sql.window import Window

    v = fixed(spark, sf)
    s = ivf.assign(v, ivf.seeds(v, lists_for(v))).groupBy(F.col("list_id").cast("long").alias("list_id")).agg(F.count("*").alias("n"))
    w = Window.partitionBy()  # a row a list
    return s.select("list_id", "n", F.sum("n").over(w).alias("total"), F.expr("max(n) OVER () * 1000 DIV (sum(n) OVER () DIV count(*) OVER ())").alias("skew"))


def _ivf_hits(probes: str) -> str:
    return f"""inner_pairs AS (SELECT p.id AS q, m.id AS c, p.probe FROM probe p JOIN member m ON p.list_id = m.list_id AND p.id <> m.id AND p.id % 20 = 0),
scored AS (SELECT q, c, probe, sum(a.val * b.val)::BIGINT AS dot FROM inner_pairs JOIN vecs a ON a.id = q JOIN vecs b ON b.id = c AND b.dim = a.dim GROUP BY ALL),
cosine AS (SELECT q, c, probe, dot / sqrt((a.n2 * b.n2)::DOUBLE) AS score FROM scored JOIN norms a ON q = a.id JOIN norms b ON c = b.id),
hits AS ({probes})"""


@query(f"WITH {sql.inverted(4)}, {_ivf_hits(f'SELECT q, c, score, row_number() OVER (PARTITION BY q ORDER BY score DESC, c)::INT AS rank FROM cosine QUALIFY rank <= {TOP}')} SELECT q, c, score, rank FROM hits")
def ivf_search(spark: SparkSession, sf: str) -> DataFrame:
    v = fixed(spark, sf)
    return ivf.search(asked(v), v, ivf.seeds(v, lists_for(v)), TOP, 4)


PROBES = (1, 4, 8)


@query(f"""WITH {sql.inverted(8)}, {_PAIRS}, {_EXACT}, {_ivf_hits(f'SELECT n_probe, q, c FROM cosine, (SELECT unnest([1, 4, 8]) AS n_probe) WHERE probe < n_probe QUALIFY row_number() OVER (PARTITION BY n_probe, q ORDER BY score DESC, c) <= {TOP}')},
scan AS (SELECT n_probe, count(*) AS scanned FROM cosine, (SELECT unnest([1, 4, 8]) AS n_probe) WHERE probe < n_probe GROUP BY n_probe)
SELECT n_probe, count(*) AS found, (SELECT count(*) FROM exact) AS wanted, any_value(scanned) AS scanned FROM hits JOIN exact USING (q, c) JOIN scan USING (n_probe) GROUP BY n_probe""")
def ivf_recall(spark: SparkSession, sf: str) -> DataFrame:
    """Recall of the exact top 10 and vectors compared, by the number of probed lists."""
    v = written(fixed(spark, sf))
    index = ivf.Index.build(v, ivf.seeds(v, lists_for(v)))
    q = written(asked(v))
    exact, own = written(flat.search(q, v, TOP)), q.count()
    out = None
    for p in PROBES:
        scanned = index.scanned(q, p).select((F.col("scanned") - own).alias("scanned"))  # without the queries themselves
        r = metrics.recall_at(index.search(q, TOP, p), exact).crossJoin(scanned).select(F.lit(p).alias("n_probe"), "found", "wanted", "scanned")  # one row each
        out = r if out is None else out.unionByName(r)
    return out


@query(f"""WITH {sql.fixed()}, codes AS (SELECT id, dim, floor(val / {quantized.STEP})::BIGINT AS val FROM vecs), code_norm AS (SELECT id, sum(val * val)::BIGINT AS n2 FROM codes GROUP BY id),
near AS (SELECT a.id AS q, b.id AS c, sum(a.val * b.val)::BIGINT AS dot FROM codes a JOIN codes b ON a.dim = b.dim AND a.id <> b.id WHERE a.id % 20 = 0 GROUP BY ALL),
best AS (SELECT q, c FROM near JOIN code_norm x ON q = x.id JOIN code_norm y ON c = y.id QUALIFY row_number() OVER (PARTITION BY q ORDER BY dot / sqrt((x.n2 * y.n2)::DOUBLE) DESC, c) <= 40),
again AS (SELECT q, c, sum(a.val * b.val)::BIGINT AS dot FROM best JOIN vecs a ON a.id = q JOIN vecs b ON b.id = c AND a.dim = b.dim GROUP BY ALL)
SELECT q, c, dot / sqrt((x.n2 * y.n2)::DOUBLE) AS score, row_number() OVER (PARTITION BY q ORDER BY dot / sqrt((x.n2 * y.n2)::DOUBLE) DESC, c)::INT AS rank FROM again JOIN norms x ON q = x.id JOIN norms y ON c = y.id QUALIFY rank <= {TOP}""")
def sq8_search(spark: SparkSession, sf: str) -> DataFrame:
    v = fixed(spark, sf)
    return quantized.scalar_search(asked(v), v, TOP, 4 * TOP)


_PARTS, _WORDS = 8, 16


@query(f"""WITH {sql.fixed()}, books AS (SELECT id, row_number() OVER (ORDER BY md5(id::VARCHAR)) - 1 AS word FROM norms QUALIFY word < {_WORDS}),
sub AS (SELECT id, dim // {_PARTS} AS part, dim, val FROM vecs), code_words AS (SELECT word, part, dim, val FROM sub JOIN books USING (id)),
gap AS (SELECT s.id, s.part, word, sum((s.val - w.val) * (s.val - w.val))::BIGINT AS d FROM sub s JOIN code_words w ON s.dim = w.dim GROUP BY ALL),
codes AS (SELECT id, part, word FROM gap QUALIFY row_number() OVER (PARTITION BY id, part ORDER BY d, word) = 1),
looks AS (SELECT s.id AS q, s.part, word, sum(s.val * w.val)::BIGINT AS dot FROM sub s JOIN code_words w ON s.dim = w.dim GROUP BY ALL),
sums AS (SELECT q, c.id AS c, sum(dot)::DOUBLE AS score FROM looks l JOIN codes c ON l.part = c.part AND l.word = c.word AND l.q <> c.id WHERE l.q % 20 = 0 GROUP BY ALL)
SELECT q, c, score, row_number() OVER (PARTITION BY q ORDER BY score DESC, c)::INT AS rank FROM sums QUALIFY rank <= {TOP}""")
def pq_search(spark: SparkSession, sf: str) -> DataFrame:
    """Product codes whose words are slices of the seeds, scored by table look-ups."""
    v = fixed(spark, sf)
    return quantized.product_search(asked(v), v, TOP, _PARTS, quantized.seed_books(v, _PARTS, _WORDS))


@query()
def hnsw_search(spark: SparkSession, sf: str) -> DataFrame:
    v = fixed(spark, sf)
    return hnsw.search_shards(asked(v), v, TOP)


@query(f"WITH {sql.fixed()} SELECT a.dim AS i, b.dim AS j, sum(a.val * b.val)::DOUBLE AS s FROM vecs a JOIN vecs b ON a.id = b.id AND a.dim <= b.dim GROUP BY ALL")
def gram_matrix(spark: SparkSession, sf: str) -> DataFrame:
    return pca.gram(fixed(spark, sf)).select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), "s")


#: Frozen integer components (4 x 64) of pca_project, by a rule.
FROZEN = np.array([[(7 * i + 11 * j * j) % 19 - 9 for j in range(64)] for i in range(4)])
_FROZEN_VALUES = ", ".join(f"({i}, {j}, {FROZEN[i, j]})" for i in range(4) for j in range(64))


@query(f"WITH {sql.fixed()}, frozen(k, dim, w) AS (VALUES {_FROZEN_VALUES}) SELECT id, k, sum(val * w)::DOUBLE AS y FROM vecs JOIN frozen USING (dim) GROUP BY ALL")
def pca_project(spark: SparkSession, sf: str) -> DataFrame:
    """Projection on frozen components, in long form."""
    out = pca.project(fixed(spark, sf), np.zeros(64), FROZEN.astype(float))
    return out.select("id", F.posexplode("vec").alias("k", "y"))


@query()
def pca_explained(spark: SparkSession, sf: str) -> DataFrame:
    """Share of the variance in the first 8, 16, 32 and 64 directions."""
    _, _, var = pca.fit(fixed(spark, sf), 8)
    return spark.createDataFrame([(k, float(var[:k].sum() / var.sum())) for k in (8, 16, 32, 64)], "width int, share double")


@query("""WITH n AS (SELECT count(*) AS n FROM embeddings), w AS (SELECT unnest([128, 256, 512, 1024]) AS d), s AS (SELECT unnest([0, 10000000, 200000000]) AS extra)
SELECT d, CASE WHEN extra = 0 THEN n ELSE extra END AS n, 4 * (CASE WHEN extra = 0 THEN n ELSE extra END) * d AS vectors, 8 * (CASE WHEN extra = 0 THEN n ELSE extra END) AS ids,
floor((0.61::DOUBLE + 1.025::DOUBLE * ((4 * (CASE WHEN extra = 0 THEN n ELSE extra END) * d)::DOUBLE / 1073741824::DOUBLE)) * 100)::BIGINT AS gib_hundredths FROM n, w, s""")
def index_footprint(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes of vectors and ids and the modelled size in hundredths of GiB, by width, for the table, 10 million and 200 million."""
    n = load(spark, sf, "embeddings", "vec_id").count()
    rows = [(d, k, 4 * k * d, 8 * k, math.floor(metrics.modelled_gib(k, d) * 100)) for d in (128, 256, 512, 1024) for k in (n, 10_000_000, 200_000_000)]
    return spark.createDataFrame(rows, "d int, n long, vectors long, ids long, gib_hundredths long")


ASKED = f"listing_id % {EVERY} = 0"


def offer_candidates(o: DataFrame, top: int, probes: int = LIST_PROBES) -> DataFrame:
    """q, c, score, rank: for every EVERY-th listing the nearest others by title in the closest lists."""
    v, index = text_index(o, "listing_id", "title")
    return index.search(asked(v), top, probes, positive=True)


def offer_candidates_sql(top: int, probes: int = LIST_PROBES, who: str = ASKED) -> str:
    return f"{sql.OFFERS}, {sql.dense('offers', 'listing_id', 'title')}, {sql.text_lists('offers', 'listing_id', who, probes, top)}"


@query(f"WITH {offer_candidates_sql(TOP)} SELECT q, c, score, rank FROM candidates")
def ivf_offer_candidates(spark: SparkSession, sf: str) -> DataFrame:
    """Top candidates of a query set of listings through stored inverted lists over all listings."""
    return offer_candidates(written(listings.offers(spark, sf)), TOP)


@query(f"""WITH {offer_candidates_sql(TOP, who='true')}, g AS (SELECT product_key, count(*) AS g FROM offers GROUP BY 1)
SELECT count(*) AS found, (SELECT sum(least({TOP}, g - 1))::BIGINT FROM offers JOIN g USING (product_key)) AS wanted, (SELECT sum(n)::BIGINT FROM probe JOIN (SELECT list_id, count(*) AS n FROM member GROUP BY 1) USING (list_id)) AS scanned, (SELECT count(*) FROM offers) AS listings
FROM candidates JOIN offers a ON a.listing_id = q JOIN offers b ON b.listing_id = c AND a.product_key = b.product_key""")
def candidate_recall(spark: SparkSession, sf: str) -> DataFrame:
    """How many of the listings of the same product are among the top 10 of the probed lists, every listing asking; and what was scanned."""
    o = written(listings.offers(spark, sf).select("listing_id", "product_key", "title"))
    v, index = text_index(o, "listing_id", "title")
    key = lambda k: o.select(F.col("listing_id").alias(k), F.col("product_key").alias(f"p{k}"))
    found = index.search(v, TOP, LIST_PROBES, positive=True).join(key("q"), "q").join(key("c"), "c").filter("pq = pc").agg(F.count("*").alias("found"))
    wanted = o.join(o.groupBy("product_key").agg(F.count("*").alias("g")), "product_key").agg(F.sum(F.least(F.lit(TOP), F.col("g") - 1)).alias("wanted"))
    total = o.agg(F.count("*").alias("listings"))
    return found.crossJoin(wanted).crossJoin(index.scanned(v, LIST_PROBES)).crossJoin(total)  # one row each
