"""Inverted lists over clusters, stored once and scanned exactly for the closest lists."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.vectors import seed_order
from ..sources.formats import scratch, written
from .flat import FEW, MANY, ROWS, Sums, closest, matrix, ranked, small_whole, top_block, top_packed

LIST_BLOCK = 4096
#: Vectors of signed bytes take an eighth of the room of others, and more of them are scanned at a time.
PACKED = 8
#: Centroids that every task holds, at most (128-d doubles: 64 MB). More vectors make longer lists, which are scanned in parts.
MOST_LISTS = 65_536


def seeds(vectors: DataFrame, lists: int) -> np.ndarray:
    """The vectors whose ids have the smallest md5, in that order: reruns and other engines agree."""
    rows = vectors.orderBy(seed_order(F.col("id"))).limit(min(lists, MOST_LISTS)).select("vec").collect()
    return np.array([np.frombuffer(r[0], np.int8) if is_packed(vectors) else r[0] for r in rows], float)


def is_packed(vectors: DataFrame) -> bool:
    return vectors.schema["vec"].dataType.simpleString() == "binary"


def nearest_lists(x: np.ndarray, centroids: np.ndarray, probes: int) -> np.ndarray:
    """The ``probes`` closest lists of each row by cosine; ties to the smaller list. Rows are taken 512 at a time."""
    if len(x) > 512:
        return np.concatenate([nearest_lists(x[i : i + 512], centroids, probes) for i in range(0, len(x), 512)])
    probes = min(probes, len(centroids))
    if small_whole(x, centroids) and x.any(1).all() and centroids.any(1).all():
        return closest(x, centroids, probes, np.arange(len(centroids)))[1].reshape(len(x), probes)
    with np.errstate(divide="ignore", invalid="ignore"):
        s = (x @ centroids.T) / np.sqrt((x * x).sum(1)[:, None] * (centroids * centroids).sum(1)[None, :])
    s = np.nan_to_num(s, nan=-2.0)
    out = np.empty((len(x), probes), np.int64)
    for k in range(probes):
        out[:, k] = s.argmax(1)
        s[np.arange(len(x)), out[:, k]] = -np.inf
    return out


class Lists:
    """``nearest_lists`` for one batch after another; what it needs for signed bytes is prepared once a task."""

    def __init__(self, centroids: np.ndarray):
        self.centroids, self.base, self.most = centroids, None, 0
        self.few = len(centroids) >= MANY and (centroids == np.rint(centroids)).all() and np.abs(centroids).max() < 128 and centroids.any(1).all()

    def nearest(self, x: np.ndarray, probes: int) -> np.ndarray:
        probes = min(probes, len(self.centroids))
        if x.dtype == np.int8 and self.few and x.any(1).all():
            terms = Sums.terms(x)
            most = int(terms.max())
            if terms.mean() <= FEW and np.abs(self.centroids).max() * most < 1 << 15:
                if most > self.most:
                    self.base, self.most = Sums(self.centroids.astype(np.int8), np.arange(len(self.centroids)), most), most
                return np.concatenate([self.base.closest(x[i : i + ROWS], probes)[1] for i in range(0, len(x), ROWS)]).reshape(len(x), probes)
        return nearest_lists(x.astype(float), self.centroids, probes)


def assign(vectors: DataFrame, centroids: np.ndarray, probes: int = 1) -> DataFrame:
    """id, vec, list_id, probe (0 is the closest): a row per probed list."""

    def run(batches):
        import pyarrow as pa

        lists = Lists(centroids)
        for b in batches:
            x = matrix(b.column(1))
            if not len(x):
                continue
            near = lists.nearest(x, probes)
            k = near.shape[1]
            at = np.repeat(np.arange(len(x)), k)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at)), pa.array(near.ravel().astype(np.int32)), pa.array(np.tile(np.arange(k, dtype=np.int32), len(x)))], names=["id", "vec", "list_id", "probe"])

    kind = vectors.schema["vec"].dataType.simpleString()
    return vectors.select("id", "vec").mapInArrow(run, f"id long, vec {kind}, list_id int, probe int")


def lloyd_step(vectors: DataFrame, centroids: np.ndarray) -> DataFrame:
    """list_id, dim, n, val: floored means of the members, as integers."""
    member = assign(vectors, centroids).select("list_id", F.posexplode("vec").alias("dim", "x"))
    return member.groupBy("list_id", "dim").agg(F.count("*").alias("n"), F.floor(F.sum("x") / F.count("*")).alias("val"))


def train(vectors: DataFrame, lists: int, steps: int = 3, sample: int = 256) -> np.ndarray:
    """Centroids after ``steps`` Lloyd steps on a hash sample of about ``sample`` vectors a list; empty lists keep their seed."""
    c = seeds(vectors, lists)
    n = vectors.count()
    share = min(1.0, sample * lists / max(n, 1))
    fit = vectors if share == 1.0 else vectors.filter(F.pmod(F.xxhash64("id"), F.lit(1 << 30)) < share * (1 << 30))
    for _ in range(steps):
        for r in lloyd_step(fit, c).groupBy("list_id").agg(F.array_sort(F.collect_list(F.struct("dim", "val"))).alias("v")).collect():
            c[r["list_id"]] = [x["val"] for x in r["v"]]
    return c


@dataclass
class Index:
    """Vectors laid out by list: a table under ``path`` with list_id, part, id and vec, sorted by list, so that a scan of some lists
    skips the files and row groups of all others. Lists above LIST_BLOCK (PACKED times that for signed bytes, which
    queries must have then too) are cut into parts by a salt. ``sizes`` has the vectors of
    each list; centroids and sizes (MOST_LISTS at most) travel with the tasks."""

    spark: SparkSession
    path: str
    centroids: np.ndarray
    sizes: np.ndarray

    @classmethod
    def build(cls, vectors: DataFrame, centroids: np.ndarray, path: str | None = None) -> Index:
        """Every vector is assigned once."""
        spark, path = vectors.sparkSession, path or scratch(vectors.sparkSession)
        member = written(assign(vectors, centroids).select("list_id", "id", "vec"))
        sizes = np.zeros(len(centroids), np.int64)
        for r in member.groupBy("list_id").count().collect():  # a row a list
            sizes[r["list_id"]] = r["count"]
        block = LIST_BLOCK * PACKED if is_packed(vectors) else LIST_BLOCK
        parts = F.element_at(F.array(*[F.lit(int(max(1, -(-n // block)))) for n in sizes]), F.col("list_id") + 1) if len(sizes) <= 4096 else None
        if parts is None:
            counted = spark.createDataFrame([(i, int(max(1, -(-n // block)))) for i, n in enumerate(sizes)], "list_id int, parts int")
            member, parts = member.join(F.broadcast(counted), "list_id"), F.col("parts")
        rows = member.select("list_id", F.pmod(F.xxhash64("id"), parts).cast("int").alias("part"), "id", "vec")
        rows.repartitionByRange("list_id", "part").sortWithinPartitions("list_id", "part").write.parquet(f"{path}/lists")
        numbered = [(i, [float(v) for v in c], int(n)) for i, (c, n) in enumerate(zip(centroids, sizes, strict=True))]
        spark.createDataFrame(numbered, "list_id int, centroid array<double>, n long").coalesce(1).write.parquet(f"{path}/centroids")
        return cls(spark, path, centroids, sizes)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Index:
        rows = spark.read.schema("list_id int, centroid array<double>, n long").parquet(f"{path}/centroids").orderBy("list_id").collect()
        return cls(spark, path, np.array([r["centroid"] for r in rows], float), np.array([r["n"] for r in rows], np.int64))

    def rows(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/lists")

    def scanned(self, queries: DataFrame, probes: int) -> DataFrame:
        """One row, ``scanned``: vectors that queries meet."""
        sizes, centroids = self.sizes, self.centroids

        def count(batches):
            import pyarrow as pa

            lists = Lists(centroids)
            for b in batches:
                if b.num_rows:
                    yield pa.RecordBatch.from_pydict({"scanned": [int(sizes[lists.nearest(matrix(b.column(0)), probes)].sum())]})

        return queries.select("vec").mapInArrow(count, "scanned long").agg(F.sum("scanned").alias("scanned"))

    def search(self, queries: DataFrame, top: int, probes: int, others_only: bool = True, positive: bool = False) -> DataFrame:
        """q, c, score, rank among the ``probes`` closest lists of each query."""
        sizes, centroids, signed = self.sizes, self.centroids, is_packed(queries)
        block = LIST_BLOCK * PACKED if signed else LIST_BLOCK

        def ask(batches):
            import pyarrow as pa

            lists = Lists(centroids)
            for b in batches:
                x = matrix(b.column(1))
                if not len(x):
                    continue
                near = lists.nearest(x, probes)
                parts = np.maximum(1, -(-sizes[near] // block)).ravel()
                at = np.repeat(np.repeat(np.arange(len(x)), near.shape[1]), parts)
                part = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(near.ravel(), parts).astype(np.int32)), pa.array(part.astype(np.int32)), b.column(0).take(pa.array(at)), b.column(1).take(pa.array(at))], names=["list_id", "part", "id", "vec"])

        kind = queries.schema["vec"].dataType.simpleString()
        asked = queries.select("id", "vec").mapInArrow(ask, f"list_id int, part int, id long, vec {kind}")

        def scan(a, b):
            import pyarrow as pa

            kinds = pa.schema([("q", pa.int64()), ("c", pa.int64()), ("score", pa.float64())])
            if not a.num_rows or not b.num_rows:
                return kinds.empty_table()
            found = []
            q_ids, q, ids, x = a.column("id").to_numpy(), matrix(a.column("vec")), b.column("id").to_numpy(), matrix(b.column("vec"))
            if signed:
                found = top_packed(q_ids, q, ids, x, top, others_only, positive)
            for i in range(0, 0 if signed else len(q_ids), LIST_BLOCK):
                found += top_block(q_ids[i : i + LIST_BLOCK], q[i : i + LIST_BLOCK], ids, x, top, "cosine", others_only, positive)
            return pa.table([pa.array(np.concatenate(x)) for x in zip(*found, strict=True)], schema=kinds)

        hits = asked.groupBy("list_id", "part").cogroup(self.rows().groupBy("list_id", "part")).applyInArrow(scan, "q long, c long, score double")
        return ranked(hits, top)


def search(queries: DataFrame, vectors: DataFrame, centroids: np.ndarray, top: int, probes: int, others_only: bool = True, positive: bool = False) -> DataFrame:
    """The same over an index that is built for the purpose."""
    return Index.build(vectors, centroids).search(queries, top, probes, others_only, positive)


def tune(vectors: DataFrame, exact: DataFrame, lists_grid: tuple[int, ...], probes_grid: tuple[int, ...], top: int, target: float) -> list[dict]:
    """Recall for each pair of parameters; ``smallest`` marks the fewest probes that reach the target for a number of lists."""
    out, truth = [], exact.select("q", "c")
    n = truth.count()
    for lists in lists_grid:
        index, reached = Index.build(vectors, seeds(vectors, lists)), False
        for probes in probes_grid:
            recall = index.search(vectors, top, probes).select("q", "c").join(truth, ["q", "c"]).count() / max(n, 1)
            out.append({"lists": lists, "probes": probes, "recall": recall, "smallest": recall >= target and not reached})
            reached |= recall >= target
    return out
