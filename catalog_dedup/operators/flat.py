"""Exact nearest neighbours: blocks of queries against blocks of vectors, one matrix product each."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

BLOCK = 4096


def small_whole(q: np.ndarray, x: np.ndarray) -> bool:
    """Whether inner products are whole numbers that single precision holds exactly."""
    most = np.abs(q).max(initial=0) * np.abs(x).max(initial=0) * q.shape[1]
    return bool(most < 1 << 24 and (q == np.rint(q)).all() and (x == np.rint(x)).all())


def closest(q: np.ndarray, x: np.ndarray, top: int, keys: np.ndarray, own: np.ndarray | None = None, positive: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, row of x, cosine) of the best ``top`` for ``small_whole`` numbers, best first, ties to the smaller key; ``own`` has the
    key that each row of q leaves out. Single precision finds what may be among the best, with some to spare, and double precision
    decides. Zero vectors take no part."""
    dots = q.astype(np.float32) @ x.astype(np.float32).T
    qn, xn = (q * q).sum(1), (x * x).sum(1)
    near = dots * np.where(xn > 0, 1 / np.sqrt(np.maximum(xn, 1)), 0).astype(np.float32)
    near[:, xn == 0] = -np.inf
    near[qn == 0] = -np.inf
    if own is not None:
        order = np.argsort(keys, kind="stable")
        first, last = (np.searchsorted(keys[order], own, side) for side in ("left", "right"))
        n = last - first
        near[np.repeat(np.arange(len(own)), n), order[np.repeat(first - np.cumsum(n) + n, n) + np.arange(n.sum())]] = -np.inf
    count, k = near.shape[1], min(top, near.shape[1])
    wide = count // 64
    if wide >= 4 * k:  # the k-th largest of groups' maxima is no larger than the k-th largest number
        groups = near[:, : wide * 64].reshape(len(q), wide, 64).max(2)
        cut = groups.max(1) if k == 1 else np.partition(groups, wide - k, 1)[:, wide - k]
    else:
        cut = np.partition(near, count - k, 1)[:, count - k]
    with np.errstate(invalid="ignore"):
        cut = cut - np.abs(cut) * np.float32(1e-5) - np.float32(1e-6)
    r, c = np.nonzero((near >= cut[:, None]) & (near > (0 if positive else -np.inf)))
    score = dots[r, c].astype(np.float64) / np.sqrt(qn[r] * xn[c])
    order = np.lexsort((keys[c], -score, r))
    r, c, score = r[order], c[order], score[order]
    begins = np.searchsorted(r, np.arange(len(q)))
    keep = np.arange(len(r)) - begins[r] < k
    return r[keep], c[keep], score[keep]


#: Columns of which ``Sums`` keeps the largest product, rows that it takes at a time, and vectors from which it is worth its preparation.
WIDE, ROWS, MANY = 64, 256, 2048
#: Terms of a query on average up to which adding them up beats a matrix product.
FEW = 24


class Sums:
    """``closest`` for rows of signed bytes with few numbers that are not 0, such as hashed titles: a product with all vectors is a sum of
    rows of their transpose, exact in 8 or 16 bits. Vectors lie by squared norm, in groups padded to WIDE, so that in a group the largest
    product is the largest cosine: only groups that may hold one of the best are looked at."""

    def __init__(self, x: np.ndarray, keys: np.ndarray, most_terms: int):
        n2 = np.einsum("ij,ij->i", x, x, dtype=np.int64)
        order = np.lexsort((keys, n2))
        order = order[n2[order] > 0]
        begins = np.flatnonzero(np.diff(n2[order], prepend=-1))
        sizes = np.diff(np.append(begins, len(order)))
        room = -(-sizes // WIDE) * WIDE
        at = np.arange(len(order)) + np.repeat(np.cumsum(room) - room - begins, sizes)
        self.at = np.full(room.sum(), -1)  # the row of x of each column, -1 for padding
        self.at[at] = order
        self.keys, self.n2, self.group_n2 = keys, n2, np.repeat(n2[order[begins]], room // WIDE)
        kind = np.int8 if int(np.abs(x).max(initial=0)) * most_terms < 128 else np.int16
        turned = np.zeros((2 * x.shape[1], len(self.at)), kind)
        turned[: x.shape[1], at] = x[order].T
        np.negative(turned[: x.shape[1]], out=turned[x.shape[1] :])
        self.rows, self.held = list(turned), np.empty((ROWS, len(self.at)), kind)
        self.repeats = int(np.unique(keys, return_counts=True)[1].max(initial=1))

    @staticmethod
    def terms(q: np.ndarray) -> np.ndarray:
        """Rows that are added up for each query."""
        return np.abs(q).sum(1, dtype=np.int64)

    def products(self, q: np.ndarray) -> np.ndarray:
        row, dim = np.nonzero(q)
        v = q[row, dim].astype(np.int64)
        n = np.abs(v)
        each = np.repeat(np.where(v > 0, dim, dim + q.shape[1]), n).tolist()
        ends = np.cumsum(np.bincount(row, n, len(q)).astype(np.int64)).tolist()
        out, rows, add, begin = self.held[: len(q)], self.rows, np.add, 0
        for total, end in zip(out, ends, strict=True):
            if end - begin < 2:
                total[:] = rows[each[begin]] if end > begin else 0
            else:
                add(rows[each[begin]], rows[each[begin + 1]], total)
                for k in range(begin + 2, end):
                    add(total, rows[each[k]], total)
            begin = end
        return out

    def closest(self, q: np.ndarray, top: int, own: np.ndarray | None = None, positive: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Like the function of this name. At most ROWS queries at a time."""
        dots, groups = self.products(q).reshape(len(q), -1, WIDE), len(self.group_n2)
        qn, wanted = np.einsum("ij,ij->i", q, q, dtype=np.int64), top + (self.repeats if own is not None else 0)
        bound = dots.max(2) / np.sqrt(self.group_n2)
        cut = np.partition(bound, groups - wanted, 1)[:, groups - wanted] if groups > wanted else np.zeros(len(q))
        # Padding counts as 0: where the cut is not above, every group is looked at.
        cut = np.where(cut > 0, cut * (1 - 1e-9), 0 if positive else -np.inf)
        r, g = np.nonzero((bound >= cut[:, None]) & (qn > 0)[:, None])
        near, least = dots[r, g], np.maximum(np.ceil(cut[r] * np.sqrt(self.group_n2[g]) - 1e-6), 1 if positive else -32768).astype(dots.dtype if positive else np.int16)
        each, c = np.divmod(np.flatnonzero(near >= least[:, None]), WIDE)
        dot, r, c = near[each, c].astype(np.float64), r[each], self.at[g[each] * WIDE + c]
        keep = c >= 0
        if own is not None:
            keep &= self.keys[c] != own[r]
        dot, r, c = dot[keep], r[keep], c[keep]
        score = dot / np.sqrt((qn[r] * self.n2[c]).astype(np.float64))
        order = np.lexsort((self.keys[c], -score, r))
        r, c, score = r[order], c[order], score[order]
        keep = np.arange(len(r)) - np.searchsorted(r, np.arange(len(q)))[r] < top
        return r[keep], c[keep], score[keep]


def first_of_equal(x: np.ndarray, keys: np.ndarray, most: int) -> np.ndarray:
    """Places of the ``most`` smallest keys of each vector of signed bytes, equal vectors being next to each other by a hash: of vectors that
    are equal, others cannot be among the best."""
    if x.shape[1] % 8:
        return np.arange(len(x))
    words = np.ascontiguousarray(x).view(np.int64)
    order = np.lexsort((keys, words @ np.random.default_rng(0).integers(1, 1 << 62, words.shape[1])))
    new = np.append(True, (words[order[1:]] != words[order[:-1]]).any(1))
    begins = np.flatnonzero(new)
    return np.sort(order[np.arange(len(x)) - begins[np.cumsum(new) - 1] < most])


def top_packed(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, top: int, others_only: bool, positive: bool) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """``top_block`` by cosine for signed bytes."""
    keep = first_of_equal(x, ids, top + int(np.unique(ids, return_counts=True)[1].max()))
    ids, x, terms, out = ids[keep], x[keep], Sums.terms(q), []
    if len(x) < MANY or terms.mean() > FEW or int(np.abs(x).max()) * int(terms.max()) >= 1 << 15:
        for i in range(0, len(x), BLOCK):
            out += top_block(q_ids, q.astype(np.float64), ids[i : i + BLOCK], x[i : i + BLOCK].astype(np.float64), top, "cosine", others_only, positive)
        return out
    base = Sums(x, ids, int(terms.max()))
    for i in range(0, len(q), ROWS):
        r, c, score = base.closest(q[i : i + ROWS], top, q_ids[i : i + ROWS] if others_only else None, positive)
        out.append((q_ids[i + r], ids[c], score))
    return out


def top_block(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, top: int, metric: str, others_only: bool, positive: bool) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(query, candidate, score) of the best ``top`` per query in one block; integers stay exact in double precision."""
    if metric == "cosine" and small_whole(q, x):
        out = []
        for i in range(0, len(q), 512):
            r, c, score = closest(q[i : i + 512], x, top, ids, q_ids[i : i + 512] if others_only else None, positive)
            out.append((q_ids[i + r], ids[c], score))
        return out
    dots = q @ x.T
    qn, xn = (q * q).sum(1), (x * x).sum(1)
    with np.errstate(divide="ignore", invalid="ignore"):
        score = dots / np.sqrt(qn[:, None] * xn[None, :]) if metric == "cosine" else dots if metric == "dot" else -(qn[:, None] + xn[None, :] - 2 * dots)
    bad = ~np.isfinite(score)
    if others_only:
        bad |= q_ids[:, None] == ids[None, :]
    if positive:
        bad |= dots <= 0
    score[bad] = -np.inf
    out = []
    k = min(top, len(ids))
    for i in range(len(q_ids)):
        cut = np.partition(score[i], len(ids) - k)[len(ids) - k]
        near = np.flatnonzero((score[i] >= cut) & (score[i] > -np.inf))
        near = near[np.lexsort((ids[near], -score[i][near]))][:k]
        out.append((np.full(len(near), q_ids[i]), ids[near], score[i][near]))
    return out


def matrix(column) -> np.ndarray:
    """The rows of an Arrow column of vectors: arrays in double precision, binary as signed bytes."""
    c = column.combine_chunks() if hasattr(column, "combine_chunks") else column
    if str(c.type) == "binary":  # signed bytes, as many a row
        if not len(c):
            return np.zeros((0, 0), np.int8)
        ends = np.frombuffer(c.buffers()[1], np.int32)[c.offset : c.offset + len(c) + 1]
        return np.frombuffer(c.buffers()[2], np.int8)[ends[0] : ends[-1]].reshape(len(c), -1)
    flat = c.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(c), -1) if len(c) else np.zeros((0, 0))


def search(queries: DataFrame, base: DataFrame, top: int, metric: str = "cosine", others_only: bool = True, positive: bool = False, block: int = BLOCK) -> DataFrame:
    """q, c, score, rank for ``queries`` and ``base`` (id, vec). Each block of queries meets each block of vectors once; a task
    holds one of either. Scores of metric l2 are negative squared distances."""
    nq, nb = (max(1, -(-df.count() // block)) for df in (queries, base))
    side = lambda df, own, n, other, m: df.select(F.pmod(F.xxhash64("id"), F.lit(n)).cast("int").alias(own), F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias(other), "id", "vec")
    left, right = side(queries, "bq", nq, "bx", nb), side(base, "bx", nb, "bq", nq)

    def meet(a, b):
        import pyarrow as pa

        kinds = pa.schema([("q", pa.int64()), ("c", pa.int64()), ("score", pa.float64())])
        if not a.num_rows or not b.num_rows:
            return kinds.empty_table()
        found = top_block(a.column("id").to_numpy(), matrix(a.column("vec")), b.column("id").to_numpy(), matrix(b.column("vec")), top, metric, others_only, positive)
        return pa.table([pa.array(np.concatenate(x)) for x in zip(*found, strict=True)], schema=kinds)

    hits = left.groupBy("bq", "bx").cogroup(right.groupBy("bq", "bx")).applyInArrow(meet, "q long, c long, score double")
    return ranked(hits, top)


def ranked(hits: DataFrame, top: int) -> DataFrame:
    """The best ``top`` of each query over all blocks; the rank filter lets Spark cut groups before the shuffle."""
    w = Window.partitionBy("q").orderBy(F.desc("score"), "c")
    return hits.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= top)
