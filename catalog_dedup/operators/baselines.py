"""What the matcher is compared with: keywords, one cut, a cut a leaf, rules and a stand-in for an outside service."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import text as tx
from ..sources.formats import open_store, scratch, written
from .flat import ranked

BANDS, ROWS = 8, 2
#: Permutations of token hashes (32 bits): h -> (h * factor + shift) modulo PRIME, products below 2^63.
PRIME = 4_294_967_311
K1, B = 1.2, 0.75
#: Texts and postings in a block, at most, queries scored at once, and the texts of a block that a token of the matrix product is in, at least.
GRID, POSTINGS, QUERIES, DENSE = 4096, 1_500_000, 256, 16


def permutation(k: int) -> tuple[int, int]:
    """Factor and shift of the k-th permutation, by rule."""
    return 500_000_003 + 7_919_317 * k, 1_000_003 * (k + 1)


def blocks(keyed: DataFrame) -> DataFrame:
    """k, rep, id of every member of each block (k, id) of two or more, with the block's smallest member as ``rep``: as many rows as
    members, however large a block. Two ids are candidates of each other if and only if they share a block."""
    sized = keyed.groupBy("k").agg(F.count("*").alias("n"), F.min("id").alias("rep")).filter("n > 1").select("k", "rep")
    return keyed.join(sized, "k").select("k", "rep", "id")


def links(keyed: DataFrame) -> DataFrame:
    """a, b: each member of a block linked to the smallest one. For keys that say all (equal key, same class) no link is lost."""
    return blocks(keyed).filter("rep != id").select(F.col("rep").alias("a"), F.col("id").alias("b"))


def keyword_exact(df: DataFrame, key: str, text: str) -> DataFrame:
    """Classes of equal normalised titles, as links to the smallest member."""
    return links(df.select(F.col(key).alias("id"), tx.normalise(F.col(text)).alias("k")).filter("k != ''"))


def token_set(text: Column) -> Column:
    return F.array_join(F.array_sort(F.array_distinct(tx.tokens(text))), " ")


def keyword_all_tokens(df: DataFrame, key: str, text: str) -> DataFrame:
    """Classes of equal sets of tokens, as links to the smallest member."""
    return links(df.select(F.col(key).alias("id"), token_set(F.col(text)).alias("k")).filter("k != ''"))


def postings(df: DataFrame, key: str, text: str) -> DataFrame:
    """id, h, tf: the distinct tokens of each id's whole texts, by hash, and how often each occurs; ids without a token are left out.
    Made row by row without a shuffle; only ids that occur more than once are put together."""
    hashed = df.select(F.col(key).alias("id"), F.transform(tx.tokens(F.col(text)), lambda t: F.xxhash64(t)).alias("h")).filter("id IS NOT NULL AND size(h) > 0")

    def counted(batches):
        import pyarrow as pa

        for b in batches:
            for i in range(0, b.num_rows, 1024):
                part = b.slice(i, 1024)
                h, row = part.column(1).flatten().to_numpy(), np.repeat(np.arange(part.num_rows), part.column(1).value_lengths().to_numpy())
                order = np.lexsort((h, row))
                h, row = h[order], row[order]
                first = np.flatnonzero(np.r_[True, (h[1:] != h[:-1]) | (row[1:] != row[:-1])])
                ends = pa.array(np.r_[0, np.cumsum(np.bincount(row[first], minlength=part.num_rows))].astype(np.int32))
                lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (h[first], np.diff(np.r_[first, len(h)]).astype(np.int32))]
                yield pa.RecordBatch.from_arrays([part.column(0), *lists], names=["id", "h", "tf"])

    kind = f"id {hashed.schema['id'].dataType.simpleString()}, h array<bigint>, tf array<int>"
    rows = written(hashed.mapInArrow(counted, kind))
    twice = written(rows.groupBy("id").count().filter("count > 1").select("id"))
    if twice.isEmpty():
        return rows
    each = rows.join(twice, "id", "left_semi").select("id", F.explode(F.arrays_zip("h", "tf")).alias("x")).groupBy("id", "x.h").agg(F.sum("x.tf").cast("int").alias("tf"))
    merged = each.groupBy("id").agg(F.collect_list(F.struct("h", "tf")).alias("x")).select("id", "x.h", "x.tf")
    return written(rows.join(twice, "id", "left_anti").unionByName(merged))


def keyword_bm25(df: DataFrame, key: str, text: str, top: int, every: int = 20) -> DataFrame:
    """q, c, score, rank by BM25 with integer term weights, for the rows whose id is divisible by ``every`` against all others.

    Postings of texts, tokens of queries and token frequencies are written once. A task takes its texts a block at a time, looks up
    its tokens' frequencies, scores all queries in turn and keeps the best ``top`` of each over all its blocks: rows are neither
    repeated on disk nor shuffled for a token. Tokens in many of a block's texts are scored by a matrix product, the others from
    postings; sums of integers are exact either way. Tokens of one text alone match nothing and have no frequency."""
    spark = df.sparkSession
    rows, asking, known = postings(df, key, text), scratch(spark), scratch(spark)
    n, words = rows.agg(F.count("*"), F.sum(F.aggregate("tf", F.lit(0).cast("long"), lambda s, x: s + x))).first()
    rows.filter(F.col("id") % every == 0).select("id", "h").write.parquet(asking)
    freq = rows.select(F.explode("h").alias("h")).groupBy("h").agg(F.count("*").alias("df")).filter("df > 1")
    freq.select("h", F.floor(1000 * F.log(1 + (n - F.col("df") + 0.5) / (F.col("df") + 0.5))).alias("idf")).write.parquet(known)
    mean, at_once, dense = words / n if n else 1.0, QUERIES, DENSE

    def score(batches):
        import pyarrow as pa

        scorer = _Scorer(asking, known, mean, top, at_once, dense)
        waiting, size, count = [], 0, 0
        for b in batches:
            lengths = b.column(1).value_lengths().to_numpy()
            at = 0
            while at < len(lengths):  # blocks of GRID texts or POSTINGS postings, whichever is less
                upto = at + max(1, min(GRID - count, int(np.searchsorted(np.cumsum(lengths[at:]), max(1, POSTINGS - size), "right"))))
                waiting.append(pa.Table.from_batches([b.slice(at, upto - at)]))
                size, count, at = size + int(lengths[at:upto].sum()), count + upto - at, upto
                if size >= POSTINGS or count >= GRID or at < len(lengths):
                    scorer.block(pa.concat_tables(waiting).combine_chunks())
                    waiting, size, count = [], 0, 0
        if waiting:
            scorer.block(pa.concat_tables(waiting).combine_chunks())
        for q, c, s in scorer.best.values():
            yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(c), pa.array(s.astype(np.int64))], names=["q", "c", "score"])

    return ranked(rows.select(F.col("id").cast("long").alias("id"), "h", "tf").mapInArrow(score, "q long, c long, score long"), top)


class _Scorer:
    """Scores blocks of texts against all queries. ``best`` has (query, text, score) of the best ``top`` so far by number of the batch
    of queries."""

    def __init__(self, asking: str, known: str, mean: float, top: int, at_once: int, dense: int):
        self.asking, self.known, self.mean, self.top, self.at_once, self.dense, self.best = asking, known, mean, top, at_once, dense, {}

    @staticmethod
    def _batches(folder: str, rows: int):
        import pyarrow.dataset as ds

        store, path = open_store(folder)
        files = sorted(ds.dataset(path, format="parquet", filesystem=store).files)
        return (b for f in files for b in ds.dataset(f, format="parquet", filesystem=store).to_batches(batch_size=rows) if b.num_rows)

    def block(self, texts) -> None:
        flat = lambda c: texts.column(c).combine_chunks().flatten().to_numpy()
        ids, h, tf = texts.column("id").to_numpy(), flat("h"), flat("tf").astype(np.int64)
        n, lengths = len(ids), texts.column("h").combine_chunks().value_lengths().to_numpy()
        order = np.argsort(ids, kind="stable")
        row = np.repeat(np.argsort(order), lengths)  # texts in the order of ids
        ids, size = ids[order], np.bincount(row, tf, n)
        tokens, tok = np.unique(h, return_inverse=True)
        idf = np.full(len(tokens), -1, np.int64)
        for b in self._batches(self.known, 1 << 18):
            x = b.column("h").to_numpy()
            at = np.minimum(np.searchsorted(tokens, x), len(tokens) - 1)
            same = tokens[at] == x
            idf[at[same]] = b.column("idf").to_numpy()[same]
        use = np.flatnonzero(idf[tok] >= 0)
        use = use[np.argsort(tok[use], kind="stable")]
        tok, row, tf = tok[use], row[use], tf[use]
        w = np.floor(idf[tok] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * size[row] / self.mean)))
        first = np.searchsorted(tok, np.arange(len(tokens) + 1))
        many = np.diff(first)
        dense = np.flatnonzero(many >= max(self.dense, n // 16))
        place = np.full(len(tokens), -1)
        place[dense] = np.arange(len(dense))
        kind = np.float32 if np.bincount(row, w, n).max(initial=0) < 1 << 24 else np.float64  # whole numbers stay exact
        table, at = np.zeros((len(dense), n), kind), place[tok] >= 0
        table[place[tok[at]], row[at]] = w[at]
        free = bool((w == 0).any())  # such tokens are shared without a score

        def shared(q_row: np.ndarray, t: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """Places in the scores, and postings, of the tokens."""
            k = many[t]
            where = np.repeat(first[t] - np.cumsum(k) + k, k) + np.arange(k.sum())
            return np.repeat(q_row, k) * n + row[where], where

        for number, b in enumerate(self._batches(self.asking, self.at_once)):
            q, qh = b.column("id").to_numpy().astype(np.int64), b.column("h").flatten().to_numpy()
            q_row = np.repeat(np.arange(len(q)), b.column("h").value_lengths().to_numpy())
            t = np.minimum(np.searchsorted(tokens, qh), len(tokens) - 1)
            hit = (tokens[t] == qh) & (idf[t] >= 0)
            q_row, t = q_row[hit], t[hit]
            often = place[t] >= 0
            wanted = np.zeros((len(q), len(dense)), kind)
            wanted[q_row[often], place[t[often]]] = 1
            at, where = shared(q_row[~often], t[~often])
            s = np.bincount(at, w[where], len(q) * n).reshape(len(q), n).astype(float, copy=False)  # of nothing: integers
            s += wanted @ table
            own = np.minimum(np.searchsorted(ids, q), n - 1)
            if free and ((s > 0).sum(1) <= self.top).any():
                s[(s == 0) & (np.bincount(shared(q_row, t)[0], minlength=len(q) * n).reshape(len(q), n) > 0)] = 0.5  # below 1, above nothing
            s[np.flatnonzero(ids[own] == q), own[ids[own] == q]] = 0
            old = self.best.get(number)
            cut = np.full(len(q), 0.25)
            if old is not None:
                last = np.flatnonzero(np.bincount(np.searchsorted(np.sort(q), old[0]), minlength=len(q)) >= self.top)
                worst = np.full(len(q), np.inf)
                np.minimum.at(worst, np.searchsorted(np.sort(q), old[0]), old[2])
                by = np.argsort(np.argsort(q))
                full = np.isin(by, last)
                cut[full] = np.maximum(0.25, worst[by[full]])
            new = np.flatnonzero(cut < 0.5)
            if n > self.top and len(new):
                cut[new] = np.maximum(cut[new], np.partition(s[new], n - self.top, 1)[:, n - self.top])
            r, c = np.nonzero(s >= cut[:, None])
            found = (q[r], ids[c], s[r, c])
            if old is not None:
                found = tuple(map(np.concatenate, zip(old, found, strict=True)))
            order = np.lexsort((found[1], -found[2], found[0]))
            found = tuple(x[order] for x in found)
            begins = np.flatnonzero(np.r_[True, found[0][1:] != found[0][:-1]])[: len(found[0])]
            rank = np.arange(len(found[0])) - np.repeat(begins, np.diff(np.r_[begins, len(found[0])]))
            self.best[number] = tuple(x[rank < self.top] for x in found)


def category_thresholds(pairs: DataFrame, leaf: str, score: str, truth: str) -> DataFrame:
    """leaf, cut, tp, fp, fn: the cut with the best F1 of each leaf; ties to the higher cut."""
    at = pairs.groupBy(leaf, F.col(score).alias("cut")).agg(F.sum(F.col(truth).cast("long")).alias("p"), F.count("*").alias("n"))
    w = Window.partitionBy(leaf).orderBy(F.desc("cut")).rowsBetween(Window.unboundedPreceding, 0)
    s = at.withColumns({"tp": F.sum("p").over(w), "upto": F.sum("n").over(w), "all_p": F.sum("p").over(Window.partitionBy(leaf))})
    s = s.withColumns({"fp": F.col("upto") - F.col("tp"), "fn": F.col("all_p") - F.col("tp")})
    f1 = 2 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn"))
    return s.groupBy(leaf).agg(F.max_by(F.struct("cut", "tp", "fp", "fn"), F.struct(f1, F.col("cut"))).alias("x")).select(leaf, "x.*")


def rule_verdict(size_a: Column, size_b: Column, price_a: Column, price_b: Column, shared: Column) -> Column:
    """Equal sizes, at least two shared tokens and prices within a factor of two."""
    return (size_a == size_b) & (shared >= 2) & (price_a <= 2 * price_b) & (price_b <= 2 * price_a)


def minhash_bands(df: DataFrame, key: str, text: str) -> DataFrame:
    """id, k: two minimum hashes of the whole text's token set in each of eight bands. A token is hashed once; minima are taken in the
    partial aggregate, so a row per text and task is shuffled."""
    rows = df.select(F.col(key).alias("id"), F.explode(tx.tokens(F.col(text))).alias("tok")).select("id", tx.token_hash(F.col("tok")).alias("h"))
    least = [F.min((F.col("h") * permutation(s)[0] + permutation(s)[1]) % PRIME).alias(f"m{s}") for s in range(BANDS * ROWS)]
    mins = rows.groupBy("id").agg(*least)
    keys = [F.concat_ws("|", F.lit(str(b)), *[F.col(f"m{b * ROWS + r}").cast("string") for r in range(ROWS)]) for b in range(BANDS)]
    return mins.select("id", F.explode(F.array(*keys)).alias("k"))


def lsh_candidates(df: DataFrame, key: str, text: str) -> DataFrame:
    """Blocks of texts that share a band, with all members."""
    return blocks(minhash_bands(df, key, text))


def black_box(pairs: DataFrame, listings: DataFrame) -> DataFrame:
    """``pairs`` (a, b) with ``flagged``: what the stand-in for an outside service calls a match. It sees a shared band, an equal
    brand and unit prices within 0.8 and 1.25, and is asked about pairs, so no block is ever paired with itself."""
    bands = minhash_bands(listings, "listing_id", "title").groupBy("id").agg(F.collect_list("k").alias("bands"))
    known = listings.select("listing_id", "p_brand", "price").join(bands, F.col("listing_id") == F.col("id"), "left")
    side = lambda k: known.select(F.col("listing_id").alias(k), F.col("p_brand").alias(f"brand_{k}"), F.col("price").alias(f"price_{k}"), F.col("bands").alias(f"bands_{k}"))
    j = pairs.join(side("a"), "a").join(side("b"), "b")
    same = (F.col("brand_a") == F.col("brand_b")) & (F.col("price_a") * 0.8 <= F.col("price_b")) & (F.col("price_a") * 1.25 >= F.col("price_b"))
    return j.withColumn("flagged", F.coalesce(F.arrays_overlap("bands_a", "bands_b") & same, F.lit(False))).select(*pairs.columns, "flagged")
