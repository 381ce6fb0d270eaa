"""Quantised vectors: one byte a dimension, or product codes; both with exact scoring of the best."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.formats import written
from . import ivf
from .flat import matrix, ranked, search

STEP = 16


def scalar_codes(vectors: DataFrame, step: int = STEP) -> DataFrame:
    """id, vec (quantised: floor(x / step), a byte at 4096 a unit), exact."""
    return vectors.select("id", F.transform("vec", lambda x: F.floor(x / step).cast("int")).alias("vec"), F.col("vec").alias("exact"))


def scalar_search(queries: DataFrame, vectors: DataFrame, top: int, rerank: int) -> DataFrame:
    """q, c, score, rank: the best ``rerank`` by codes, scored exactly and cut to ``top``."""
    near = search(scalar_codes(queries).select("id", "vec"), scalar_codes(vectors).select("id", "vec"), rerank).select("q", "c")
    return exact_scores(near, queries, vectors, top)


def exact_scores(near: DataFrame, queries: DataFrame, vectors: DataFrame, top: int) -> DataFrame:
    """The best ``top`` of the pairs (q, c) by exact cosine."""
    a, b = (df.select(F.col("id").alias(k), F.col("vec").alias(f"v{k}")) for df, k in ((queries, "q"), (vectors, "c")))
    pair = near.join(a, "q").join(b, "c")
    long = F.lit(0).cast("long")
    dot = F.aggregate(F.zip_with("vq", "vc", lambda x, y: x.cast("long") * y), long, lambda s, x: s + x)
    norm = lambda v: F.aggregate(v, long, lambda s, x: s + x.cast("long") * x)
    return ranked(pair.select("q", "c", (dot / F.sqrt((norm("vq") * norm("vc")).cast("double"))).alias("score")), top)


def inverted_scalar_search(queries: DataFrame, vectors: DataFrame, centroids: np.ndarray, top: int, probes: int, rerank: int, step: int = STEP) -> DataFrame:
    """The same over inverted lists that hold codes: lists are scanned by code, the best ``rerank`` scored exactly."""
    codes = scalar_codes(vectors, step).select("id", "vec")
    index = ivf.Index.build(codes, np.floor(centroids / step))
    near = index.search(scalar_codes(queries, step).select("id", "vec"), rerank, probes).select("q", "c")
    return exact_scores(near, queries, vectors, top)


def train_products(x: np.ndarray, parts: int, words: int, steps: int = 8) -> np.ndarray:
    """Codewords (parts x words x d/parts) by k-means on each slice, seeded with the first rows."""
    out = []
    for s in np.split(x, parts, axis=1):
        c = s[:words].copy()
        for _ in range(steps):
            near = ((s[:, None, :] - c[None]) ** 2).sum(2).argmin(1)
            for k in range(len(c)):
                if (near == k).any():
                    c[k] = s[near == k].mean(0)
        out.append(c)
    return np.array(out)


def seed_books(vectors: DataFrame, parts: int, words: int) -> np.ndarray:
    """Codewords (parts x words x d/parts) from the seeds' own slices."""
    x = ivf.seeds(vectors, words)
    return np.stack(np.split(x, parts, axis=1))


def trained_books(vectors: DataFrame, parts: int, words: int, sample: int = 4096) -> np.ndarray:
    """Codewords by k-means on a sample of ``sample`` vectors."""
    return train_products(ivf.seeds(vectors, sample), parts, words)


def product_codes(vectors: DataFrame, books: np.ndarray) -> DataFrame:
    """id, code: one byte a part, the closest codeword (ties to the smaller)."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            x = matrix(b.column(1))
            if len(x):
                near = np.stack([((s[:, None, :] - c[None]) ** 2).sum(2).argmin(1) for s, c in zip(np.split(x, len(books), axis=1), books, strict=True)], 1).astype(np.uint8)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tobytes() for r in near], pa.binary())], names=["id", "code"])

    return vectors.select("id", "vec").mapInArrow(run, "id long, code binary")


def product_search(queries: DataFrame, vectors: DataFrame, top: int, parts: int, books: np.ndarray, block: int = 4096) -> DataFrame:
    """q, c, score, rank: inner products by table look-ups over product codes (no exact scoring, which shows what quantisation loses).
    Blocks of queries meet blocks of codes; a task holds a query's table of parts x words numbers and adds up what the codes pick."""
    codes = written(product_codes(vectors, books))
    nq, n = (max(1, -(-df.count() // block)) for df in (queries, codes))
    deal = lambda df, own, k, other, m, last: df.select(F.pmod(F.xxhash64("id"), F.lit(k)).cast("int").alias(own), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias(other), "id", last)

    def look(a, b):
        import pyarrow as pa

        kinds = pa.schema([("q", pa.int64()), ("c", pa.int64()), ("score", pa.float64())])
        if not a.num_rows or not b.num_rows:
            return kinds.empty_table()
        ids, code = b.column("id").to_numpy(), np.frombuffer(b"".join(b.column("code").to_pylist()), np.uint8).reshape(-1, parts)
        out = []
        for q, x in zip(a.column("id").to_pylist(), matrix(a.column("vec")), strict=True):
            table = np.einsum("pwd,pd->pw", books, x.reshape(parts, -1))
            score = table[np.arange(parts), code].sum(1)
            score[ids == q] = -np.inf
            k = min(top, len(ids))
            near = np.flatnonzero((score >= np.partition(score, len(ids) - k)[len(ids) - k]) & (score > -np.inf))
            near = near[np.lexsort((ids[near], -score[near]))][:k]
            out.append((np.full(len(near), q), ids[near], score[near]))
        return pa.table([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], schema=kinds)

    hits = deal(queries, "bq", nq, "bx", n, "vec").groupBy("bq", "bx").cogroup(deal(codes, "bx", n, "bq", nq, "code").groupBy("bq", "bx")).applyInArrow(look, "q long, c long, score double")
    return ranked(hits, top)
