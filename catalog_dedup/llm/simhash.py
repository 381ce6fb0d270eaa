"""SimHash near-duplicates through pivot distance tables.

Fingerprints come from XXH64 of word shingles. Equal fingerprints are one node, so copies never meet as pairs. Two nodes
link at ``MOST_BITS`` or fewer differing bits, and components of links give each document the smallest doc_id it can
reach.

Search for links, without loss. A node is filed under the values of every choice of two of four 16-bit blocks: nodes that
differ in two bits agree in two blocks at least. Within a bin of at most ``BIN`` nodes, tables of the distances to
``PIVOTS`` reference fingerprints discard pairs by their largest coordinate difference (the triangle inequality forbids a
link beyond ``MOST_BITS``); the exact distance verifies what survives. Members of larger bins are dealt with exactly in
another way: each stands in the 65 bins of itself and its one-bit neighbours, and two nodes link if and only if they share
such a bin, whose members (65 at most) all hang on its smallest. Both ways emit rows in proportion to the nodes.

Null texts count as empty; texts without words have fingerprint zero and link like any other. Rows with a null doc_id
belong to their component but can't name it (the id is null if no member has one). Repeated rows each get their row.
Extra columns are ignored by ``duplicate_classes``; an empty table gives no rows.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import carried, map_text, small, stash, unpacked

MOST_BITS = 2
SHINGLE = 3
BIN = 128
PIVOTS = 24


def fingerprints(texts: list[bytes | None], shingle: int = SHINGLE) -> np.ndarray:
    """64-bit fingerprints: bit b is set if it is set in over half the shingle hashes."""
    from xxhash import xxh64_intdigest

    out = np.zeros(len(texts), np.uint64)
    for k, t in enumerate(texts):
        words = t.lower().split() if t else []  # of bytes: ASCII letters and ASCII white space only
        if not words:
            continue
        if len(words) < shingle:
            hashes = [xxh64_intdigest(b" ".join(words), 42)]
        else:
            hashes = [xxh64_intdigest(b" ".join(x), 42) for x in zip(*[words[i:] for i in range(shingle)])]
        ones = np.zeros(64, np.int64)
        h = np.array(hashes, "<u8")
        for i in range(0, len(h), 65536):
            ones += np.unpackbits(h[i : i + 65536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        out[k] = np.packbits(2 * ones > len(h), bitorder="little").view("<u8")[0]
    return out


def with_fingerprint(docs: DataFrame, keep: list[str]) -> DataFrame:
    """``keep`` columns and ``_fp`` (long, the 64 bits)."""
    return map_text(docs, keep, [("_fp", T.LongType())], lambda texts: [fingerprints(texts).view(np.int64)], binary=True)


def pivot_table(fps: np.ndarray, pivots: int = PIVOTS) -> np.ndarray:
    """Distances (n x pivots, int8) of fingerprints to reference fingerprints drawn from a fixed seed."""
    refs = np.random.default_rng(20).integers(0, 2**64, pivots, dtype=np.uint64)
    return np.bitwise_count(fps[:, None] ^ refs[None, :]).astype(np.int8)


def linked_pairs(fps: np.ndarray, table: np.ndarray, most: int = MOST_BITS) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs a < b within ``most`` bits: discarded by largest coordinate difference, survivors verified."""
    a, b = np.triu_indices(len(fps), 1)
    for part in np.array_split(np.arange(table.shape[1]), 4):  # most pairs fall at the first few pivots
        near = np.abs(table[a][:, part] - table[b][:, part]).max(1) <= most
        a, b = a[near], b[near]
    near = np.bitwise_count(fps[a] ^ fps[b]) <= most
    return a[near], b[near]


def links(nodes: DataFrame) -> DataFrame:
    """Edges (a, b) that join the same components as all links between the distinct fingerprints in ``nodes`` (fp)."""
    blocks = [F.shiftrightunsigned("fp", 16 * k).bitwiseAND(0xFFFF) for k in range(4)]
    bins = F.array(*[F.struct(F.lit(n).alias("choice"), (F.shiftleft(blocks[i], 16) + blocks[j]).alias("value")) for n, (i, j) in enumerate(combinations(range(4), 2))])
    filed = nodes.select("fp", F.explode(bins).alias("x")).select("fp", "x.choice", "x.value")
    # Crowded bins are few (BIN times fewer than nodes at most): sent along if small, so that no bin is gathered for the sake of a join.
    crowded_bins = small(stash(filed.groupBy("choice", "value").agg(F.count("*").alias("n")).filter(F.col("n") > BIN).select("choice", "value"), "crowded"))
    rest = filed.join(crowded_bins, ["choice", "value"], "left_anti")
    grouped = rest.groupBy("choice", "value").agg(F.collect_list("fp").alias("members")).filter(F.size("members") > 1).select("members")

    def pairs(batches):
        for frame in batches:
            found = [np.empty((0, 2), np.int64)]
            for members in frame["members"]:
                m = np.asarray(members, np.int64)
                fps = m.view(np.uint64)
                a, b = linked_pairs(fps, pivot_table(fps))
                found.append(np.stack([m[a], m[b]], 1))
            e = np.unique(np.concatenate(found), axis=0)
            yield pd.DataFrame({"a": e[:, 0], "b": e[:, 1]})

    near = grouped.mapInPandas(pairs, "a long, b long")
    crowded = filed.join(crowded_bins, ["choice", "value"], "left_semi").select("fp").distinct()
    flips = F.concat(F.array(F.col("fp")), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda k: F.col("fp").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), k))))
    hub = crowded.select("fp", F.explode(flips).alias("point")).groupBy("point").agg(F.min("fp").alias("a"), F.collect_list("fp").alias("bs")).filter(F.size("bs") > 1)
    star = hub.select("a", F.explode("bs").alias("b")).filter("a != b").distinct()
    return near.unionByName(star)


def components(edges: DataFrame) -> DataFrame:
    """node, root (smallest node of its component) for every node of ``edges`` (a, b), by alternating large and small stars.

    Each round is written to the shared folder, so lineage stays short; a checksum tells when nothing moves.
    """
    e = stash(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u != v").distinct(), "edges")
    before = None
    while True:
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        down = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u != v").union(least.select("u", F.col("m").alias("v"))).filter("u != v").distinct()
        e = stash(down, "edges")
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            return e.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
        before = now


def classes(rows: DataFrame) -> DataFrame:
    """_node, root, component_id for every distinct fingerprint of ``rows`` (doc_id, _fp)."""
    nodes = stash(rows.groupBy(F.col("_fp").alias("fp")).agg(F.min("doc_id").alias("least")), "nodes")
    roots = stash(components(links(nodes.select("fp"))), "roots")
    named = nodes.join(roots, F.col("fp") == F.col("node"), "left").withColumn("root", F.coalesce("root", "fp"))
    names = named.groupBy("root").agg(F.min("least").alias("component_id"))
    return named.select(F.col("fp").alias("_node"), "root").join(names, "root").select("_node", "root", "component_id")


def duplicate_classes(docs: DataFrame) -> DataFrame:
    """doc_id, ``fingerprint`` (16 hex digits) and ``component_id`` of every row."""
    rows = stash(with_fingerprint(docs, ["doc_id"]), "fingerprints")
    out = rows.join(classes(rows), F.col("_fp") == F.col("_node"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("_fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` without near-duplicates: of each component the one with the smallest doc_id stays (ids that are
    null come last, ties go to the smaller fingerprint, and of repeated rows one stays)."""
    rows = stash(with_fingerprint(docs, ["doc_id"]), "fingerprints")
    named = rows.join(classes(rows), F.col("_fp") == F.col("_node")).select("doc_id", "root", F.col("_fp").alias("node"))
    return first_of_each(docs, named, with_fingerprint, "_fp")


def first_of_each(docs: DataFrame, named: DataFrame, mark, column: str) -> DataFrame:
    """One row of ``docs`` for each root of ``named`` (doc_id, node, root). ``mark`` adds a row's node as ``column``."""
    packed = docs.select(carried(docs.columns).alias("row"), "doc_id", "text")
    first = named.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("node").alias("node"))).alias("x"))
    first = stash(first.select("root", F.col("x.id").alias("f_id"), F.col("x.node").alias("f_node")), "first")
    hits = packed.join(first, F.col("doc_id").eqNullSafe(F.col("f_id"))).select("row", "text", "root", "f_node")
    hits = mark(hits, ["row", "root", "f_node"]).filter(F.col(column) == F.col("f_node"))
    turn = F.row_number().over(Window.partitionBy("root").orderBy(F.xxhash64("row")))  # repeated rows
    return hits.withColumn("turn", turn).filter("turn = 1").select(*unpacked("row", docs.columns))
