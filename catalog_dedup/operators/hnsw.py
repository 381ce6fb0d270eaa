"""Navigable small-world graphs, one per shard, all searched and merged."""

from __future__ import annotations

import heapq
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .flat import matrix, ranked

SHARD = 20_000


class Graph:
    """A layered neighbour graph over unit vectors; levels come from a hash of the id."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, m: int = 12, ef: int = 64):
        self.ids, self.m, self.ef = ids, m, ef
        self.x = x / np.maximum(np.sqrt((x * x).sum(1, keepdims=True)), 1e-12)
        u = np.array([(zlib.crc32(str(i).encode()) + 1) / 2**32 for i in ids])
        self.level = np.floor(-np.log(u) / np.log(m)).astype(int) if len(ids) else np.zeros(0, int)
        self.links: list[dict[int, list[int]]] = []
        self.top, self.entry = -1, -1
        for k in range(len(ids)):
            self._add(k)

    def _layer(self, q: np.ndarray, start: list[int], ef: int, layer: int) -> list[tuple[float, int]]:
        """The best ``ef`` nodes found from ``start``, best first."""
        seen = set(start)
        scores = self.x[start] @ q
        ahead = [(-s, n) for s, n in zip(scores, start, strict=True)]
        best = [(s, n) for s, n in zip(scores, start, strict=True)]
        heapq.heapify(ahead)
        heapq.heapify(best)
        while ahead:
            s, n = heapq.heappop(ahead)
            if -s < best[0][0] and len(best) >= ef:
                break
            new = [v for v in self.links[layer].get(n, ()) if v not in seen]
            seen.update(new)
            for v, t in zip(new, self.x[new] @ q if new else (), strict=True):
                if len(best) < ef or t > best[0][0]:
                    heapq.heappush(ahead, (-t, v))
                    heapq.heappush(best, (t, v))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted(best, key=lambda p: (-p[0], p[1]))

    def _diverse(self, found: list[tuple[float, int]], m: int) -> list[int]:
        """Neighbours nearer to the new node than to any neighbour already taken, filled up with the rest."""
        kept: list[int] = []
        for s, n in found:
            if len(kept) < m and (not kept or (self.x[kept] @ self.x[n]).max() < s):
                kept.append(n)
        return (kept + [n for _, n in found if n not in kept])[:m]

    def _add(self, k: int) -> None:
        while len(self.links) <= self.level[k]:
            self.links.append({})
        for layer in range(self.level[k] + 1):
            self.links[layer][k] = []
        if self.entry < 0:
            self.entry, self.top = k, self.level[k]
            return
        at = [self.entry]
        for layer in range(self.top, self.level[k], -1):
            at = [self._layer(self.x[k], at, 1, layer)[0][1]]
        for layer in range(min(self.top, self.level[k]), -1, -1):
            found = self._layer(self.x[k], at, self.ef, layer)
            most = 2 * self.m if layer == 0 else self.m
            self.links[layer][k] = self._diverse(found, self.m)
            for n in self.links[layer][k]:
                back = self.links[layer][n]
                back.append(k)
                if len(back) > most:
                    s = self.x[back] @ self.x[n]
                    self.links[layer][n] = self._diverse(sorted(zip(s, back, strict=True), key=lambda p: (-p[0], p[1])), most)
            at = [n for _, n in found]
        if self.level[k] > self.top:
            self.entry, self.top = k, self.level[k]

    def search(self, q: np.ndarray, top: int, ef: int) -> list[tuple[float, int]]:
        if self.entry < 0:
            return []
        q = q / max(float(np.sqrt(q @ q)), 1e-12)
        at = [self.entry]
        for layer in range(self.top, 0, -1):
            at = [self._layer(q, at, 1, layer)[0][1]]
        return self._layer(q, at, max(ef, top), 0)[:top]

    def bytes(self) -> int:
        return self.x.shape[0] * self.x.shape[1] * 4 + 8 * sum(len(v) for layer in self.links for v in layer.values())


def search_shards(queries: DataFrame, vectors: DataFrame, top: int, ef: int = 64, m: int = 12, shard: int = SHARD) -> DataFrame:
    """q, c, score, rank. A shard's graph is built where its vectors are and asked all queries (a stated query set)."""
    n = max(1, -(-vectors.count() // shard))
    base = vectors.select(F.pmod(F.xxhash64("id"), F.lit(n)).cast("int").alias("shard"), "id", "vec")
    asked = queries.select(F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("shard"), "id", "vec")

    def run(q, b):
        import pyarrow as pa

        kinds = pa.schema([("q", pa.int64()), ("c", pa.int64()), ("score", pa.float64())])
        if not q.num_rows or not b.num_rows:
            return kinds.empty_table()
        ids = b.column("id").to_numpy()
        order = np.argsort(ids)
        g = Graph(ids[order], matrix(b.column("vec"))[order], m, max(ef, 2 * m))
        out = [(i, int(g.ids[v]), float(s)) for i, x in zip(q.column("id").to_pylist(), matrix(q.column("vec")), strict=True) for s, v in g.search(x, top + 1, ef) if g.ids[v] != i]
        return pa.table([pa.array(c) for c in zip(*out, strict=True)], schema=kinds) if out else kinds.empty_table()

    return ranked(asked.groupBy("shard").cogroup(base.groupBy("shard")).applyInArrow(run, "q long, c long, score double"), top)


def graph_links(vectors: DataFrame, ef: int = 64, m: int = 12, shard: int = SHARD) -> int:
    """Links of the graphs that ``search_shards`` builds."""
    n = max(1, -(-vectors.count() // shard))
    base = vectors.select(F.pmod(F.xxhash64("id"), F.lit(n)).cast("int").alias("shard"), "id", "vec")

    def count(b):
        import pyarrow as pa

        ids = b.column("id").to_numpy()
        order = np.argsort(ids)
        g = Graph(ids[order], matrix(b.column("vec"))[order], m, max(ef, 2 * m))
        return pa.table([pa.array([sum(len(x) for layer in g.links for x in layer.values())], pa.int64())], names=["links"])

    return base.groupBy("shard").applyInArrow(count, "links long").agg(F.sum("links")).first()[0] or 0
