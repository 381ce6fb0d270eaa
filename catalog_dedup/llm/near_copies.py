"""Near copies at a word-shingle Jaccard similarity: SimHash in sorted tables, then an exact search for what the tables miss.

A text's set of 5-word shingles (lower-cased ASCII, words between ASCII white space; shorter texts are one shingle) has a
fingerprint of 128 bits; texts with equal sets are one node. Every node enters ``TABLES`` tables, each sorted by the fingerprint with
its bits in another order, and meets the ``REACH`` nodes that follow it there. Pairs that meet are thinned by pivot distance tables (the
largest coordinate difference is at most the distance) and by exact distance; what is left is verified by the exact Jaccard. This
joins most groups with few pairs a node.

No link is lost, whatever the tables miss. A set's shingles have one order (rare ones of a sample first, then by hash; any order is
right), and two sets that reach the similarity share one of each other's first fifth. So each node is filed under those shingles.
Nodes of one component have nothing left to settle; others under a shingle are written as pairs if that makes at most ``FEW`` a member.
More are compared where they meet: their parities of hashed shingles go to cells of at most two blocks of members, and only pairs
that the parities allow are written. Under a crowded shingle (over ``STAR`` pairs a member) all members are first compared with one
of them, which joins groups of copies in proportion to their size. Those still apart under a shingle of over ``PAIRS`` a member are
filed anew under that shingle and a second one, then a third, and are compared in cells thereafter. Pairs are thinned by their sizes,
by what can follow the shared shingle and by the parities, all of which are bounds, and verified.

Verification of what the tables found goes round by round, and leaves out what can change nothing: each node's closest pairs first,
then the components of the verified links are formed, and pairs within a component need no verification. Rounds look at four times
more pairs of a node than the one before and end when no pair is left.

Null texts and texts without words are one node without shingles. Rows may repeat. An empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from . import common as shared
from .common import discard, map_text, release, small, stash, uniform
from .simhash import components, first_of_each

SHINGLE, SIMILARITY = 5, 0.8
#: Most differing bits that tables look at (two sets at the similarity differ in about 19).
MOST_BITS = 29
REACH, TABLES = 4, 8
PIVOTS = 8
#: Pairs a member that a shingle may make: as written pairs, compared at once in cells, and compared in cells after members have met
#: one of them. After so many shingles more, all members are compared.
FEW, STAR, PAIRS, LEVELS = 4, 64, 2048, 2
#: Members in a block of a cell, and pairs that are held at a time.
BLOCK, HELD = 512, 1 << 18
#: The sample that puts rare shingles first: texts at least (about), their least share, and shingles at most.
SAMPLE, SHARE, COMMON = 4000, 1 / 32, 500_000
#: Bits of parities of every set, and at most of the wider ones of sets for which those are too few.
PARITIES, MOST_PARITIES = 512, 1 << 16


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        from xxhash import xxh3_64_intdigest

        if len(self) > 300_000:
            self.clear()
        h = self[word] = xxh3_64_intdigest(word)
        return h


def _mixed(x: np.ndarray, add: int) -> np.ndarray:
    x = x + np.uint64(add)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(31))


def shingle_set(text: bytes | None, hash_of: dict, size: int = SHINGLE) -> np.ndarray:
    """Sorted hashes of the distinct shingles."""
    words = text.lower().split() if text else []
    h = np.fromiter(map(hash_of.__getitem__, words), np.uint64, len(words))
    if not len(h):
        return h
    k = min(size, len(h))
    out = np.zeros(len(h) - k + 1, np.uint64)
    for i in range(k):
        out = _mixed(out ^ h[i : len(h) - k + 1 + i], 0x9E3779B97F4A7C15)
    return np.unique(out)


def fingerprint(shingles: np.ndarray) -> bytes:
    """128 bits, each set if it is set in over half of the shingles' hashes."""
    ones = np.zeros(128, np.int64)
    for i in range(0, len(shingles), 16384):
        part = shingles[i : i + 16384]
        wide = np.stack([part, _mixed(part, 0xD1B54A32D192ED03)], 1)
        ones += np.unpackbits(wide.view(np.uint8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return np.packbits(2 * ones > len(shingles), bitorder="little").tobytes()


def _node(shingles: np.ndarray) -> int:
    from xxhash import xxh3_64_intdigest

    h = xxh3_64_intdigest(shingles.tobytes())
    return h - (1 << 64) if h >= 1 << 63 else h


def least_shared(size: int, similarity: float) -> int:
    """Shingles that a set of this size shares with any other at the similarity, at least."""
    return math.ceil(similarity * size - 1e-6)


def in_order(shingles: np.ndarray, common: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Shingles (sorted) in the order of all sets: those not among the ``common`` (sorted hashes, counts) first, then rarer ones."""
    if not len(common[0]) or not len(shingles):
        return shingles
    at = np.minimum(np.searchsorted(common[0], shingles), len(common[0]) - 1)
    return shingles[np.argsort(np.where(common[0][at] == shingles, common[1][at], 0), kind="stable")]


def parities(shingles: np.ndarray, bits: int = PARITIES) -> bytes:
    """A bit a slot that tells if an odd number of shingles falls into it: two sets differ in as many shingles at least as in bits."""
    odd = np.bincount((shingles % np.uint64(bits)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def wide_parities(shingles: np.ndarray) -> bytes:
    """Two to four bits a shingle, a power of two, for sets of over half as many shingles as PARITIES."""
    return parities(shingles, min(MOST_PARITIES, 2 << len(shingles).bit_length())) if 2 * len(shingles) > PARITIES else b""


def differing(x: list[bytes], y: list[bytes]) -> np.ndarray:
    """Differing bits of pairs of parities. Those of more bits are folded to as few as the other has; none differ if one is empty."""
    nx, ny = (np.array([len(v) for v in z], np.int64) for z in (x, y))
    out = np.zeros(len(nx), np.int64)
    for i, j in {*zip(nx.tolist(), ny.tolist(), strict=True)}:
        if not (width := min(i, j)):
            continue
        at = np.flatnonzero((nx == i) & (ny == j))
        u, v = (np.bitwise_xor.reduce(np.frombuffer(b"".join([z[k] for k in at]), np.uint8).reshape(len(at), -1, width), 1) for z in (x, y))
        out[at] = np.bitwise_count(u ^ v).sum(1)
    return out


def common_shingles(docs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes and counts of shingles that several texts of a hash sample hold. They only set an order."""
    share = min(1.0, max(SHARE, SAMPLE / max(docs.count(), 1)))

    def run(batches):
        import pyarrow as pa

        hash_of = _Hashes()
        for b in batches:
            found = [shingle_set(t, hash_of) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(found).view(np.int64) if found else np.zeros(0, np.int64))], names=["h"])

    texts = docs.filter(uniform(F.col("doc_id")) < share).select(F.col("text").cast("binary"))
    counted = texts.mapInArrow(run, "h long").groupBy("h").agg(F.count("*").alias("n")).filter("n > 1").orderBy(F.desc("n"), "h").limit(COMMON).toArrow()
    h, n = counted.column("h").to_numpy().view(np.uint64), counted.column("n").to_numpy()
    order = np.argsort(h)
    return h[order], n[order].astype(np.int32)


#: What ``with_node`` can tell of a set beside its node.
_MADE = {"s_print": (T.BinaryType(), lambda s, *_: fingerprint(s)), "s_set": (T.BinaryType(), lambda s, *_: s.tobytes()), "s_size": (T.IntegerType(), lambda s, *_: len(s)), "s_odd": (T.BinaryType(), lambda s, *_: parities(s)), "s_wide": (T.BinaryType(), lambda s, *_: wide_parities(s)), "s_first": (T.BinaryType(), lambda s, common, t: in_order(s, common)[: len(s) - least_shared(len(s), t) + 1].tobytes())}


def with_node(docs: DataFrame, keep: list[str], *more: str, common: tuple | None = None, similarity: float = SIMILARITY) -> DataFrame:
    """``keep`` columns, ``s_node`` (a long that tells the shingle set) and of ``more`` the fingerprint ``s_print``, the set ``s_set``,
    its size ``s_size``, its parities ``s_odd`` and ``s_wide`` and the shingles it is filed under ``s_first``."""
    held: list[_Hashes] = []

    def run(texts: list) -> list:
        if not held:
            held.append(_Hashes())
        sets = [shingle_set(t, held[0]) for t in texts]
        made = [[_MADE[m][1](s, common, similarity) for s in sets] for m in more]
        return [[_node(s) for s in sets], *[np.array(x, np.int32) if m == "s_size" else x for m, x in zip(more, made, strict=True)]]

    return map_text(docs, keep, [("s_node", T.LongType()), *[(m, _MADE[m][0]) for m in more]], run, binary=True)


def candidates(nodes: DataFrame, tables: int = TABLES) -> DataFrame:
    """a < b and their distance: pairs that meet in a table, within MOST_BITS."""
    orders = [np.random.default_rng(1000 + t).permutation(128) for t in range(tables)]
    refs = np.random.default_rng(20).integers(0, 256, (PIVOTS, 16), dtype=np.uint8)

    def enter(batches):
        import pyarrow as pa

        for b in batches:
            for i in range(0, b.num_rows, 4096):
                part = b.slice(i, 4096)
                bits = np.unpackbits(np.frombuffer(b"".join(part.column(1).to_pylist()), np.uint8).reshape(-1, 16), axis=1, bitorder="little")
                for t, order in enumerate(orders):
                    data = np.packbits(bits[:, order], axis=1).tobytes()
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(bits), t, np.int32)), pa.array([data[k : k + 16] for k in range(0, len(data), 16)], pa.binary()), part.column(0)], names=["t", "key", "node"])

    def meet(batches):
        """Neighbours in order; the last REACH rows of a batch wait for the next."""
        import pyarrow as pa

        kinds = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("d", pa.int32())])
        t0, x0, n0 = np.zeros(0, np.int32), np.zeros((0, 16), np.uint8), np.zeros(0, np.int64)
        for b in batches:
            if not b.num_rows:
                continue
            came = len(t0)
            t = np.r_[t0, b.column(0).to_numpy()]
            x = np.concatenate([x0, np.frombuffer(b"".join(b.column(1).to_pylist()), np.uint8).reshape(-1, 16)])
            n = np.r_[n0, b.column(2).to_numpy()]
            words, coordinates = np.ascontiguousarray(x).view(np.uint64), np.stack([np.bitwise_count((x ^ r).view(np.uint64)).sum(1) for r in refs], 1).astype(np.int16)
            found = []
            for w in range(1, REACH + 1):
                i = np.arange(max(0, came - w), len(t) - w)  # pairs with a row of this batch
                i = i[t[i] == t[i + w]]
                i = i[np.abs(coordinates[i] - coordinates[i + w]).max(1) <= MOST_BITS] if len(i) else i
                d = np.bitwise_count(words[i] ^ words[i + w]).sum(1).astype(np.int32)
                near = d <= MOST_BITS
                i, d = i[near], d[near]
                found.append(np.stack([np.minimum(n[i], n[i + w]), np.maximum(n[i], n[i + w]), d], 1))
            pairs = np.unique(np.concatenate(found), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1]), pa.array(pairs[:, 2].astype(np.int32))], schema=kinds)
            t0, x0, n0 = t[-REACH:], x[-REACH:], n[-REACH:]

    entered = nodes.select("s_node", "s_print").mapInArrow(enter, "t int, key binary, node long")
    # Pivots see permuted bits; distances are the same in every order. Neighbours on both sides of a border between tasks are left to other tables.
    return entered.repartitionByRange("t", "key").sortWithinPartitions("t", "key", "node").mapInArrow(meet, "a long, b long, d int").distinct()


def verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Those pairs (a, b) whose sets reach the similarity."""
    side = lambda k: sets.select(F.col("s_node").alias(k), F.col("s_set").alias(f"s{k}"))

    def check(batches):
        import pyarrow as pa

        for b in batches:
            good = []
            for x, y in zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True):
                both = len(np.intersect1d(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), assume_unique=True))
                good.append(both >= similarity * ((len(x) + len(y)) // 8 - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(good, pa.bool_()))

    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "sa", "sb").mapInArrow(check, "a long, b long")


def sets_of(docs: DataFrame, nodes: DataFrame, wanted: DataFrame) -> DataFrame:
    """s_node and s_set of the ``wanted`` nodes, from one text of each."""
    chosen = stash(nodes.join(wanted, "s_node", "left_semi").select(F.col("s_node").alias("c_node"), F.col("doc_id").alias("c_id")), "chosen")
    packed = docs.select("doc_id", "text").join(small(chosen), F.col("doc_id").eqNullSafe(F.col("c_id"))).select("c_node", "text")
    return stash(with_node(packed, ["c_node"], "s_set").filter("s_node = c_node").dropDuplicates(["s_node"]).select("s_node", "s_set"), "sets")


def joined(links: DataFrame) -> DataFrame:
    """node, root of ``links`` (stashed) for all nodes but roots, like ``components``: few links (as many as a table that is broadcast has) in one task and one
    job, more by its rounds."""

    def run(batches):
        import pyarrow as pa

        parts = [np.stack([c.to_numpy() for c in b.columns], 1) for b in batches if b.num_rows]
        node, e = np.unique(np.concatenate(parts) if parts else np.zeros((0, 2), np.int64), return_inverse=True)
        e, root, before = e.reshape(-1, 2), np.arange(len(node)), None
        while before is None or (root != before).any():
            before, least = root, root[e].min(1)
            root = root.copy()
            for k in (0, 1):
                np.minimum.at(root, e[:, k], least)
                np.minimum.at(root, before[e[:, k]], least)
            root = root[root]
        k = np.flatnonzero(root != np.arange(len(node)))
        yield pa.RecordBatch.from_arrays([pa.array(node[k]), pa.array(node[root[k]])], names=["node", "root"])

    if links.limit(shared.BROADCAST_ROWS + 1).count() > shared.BROADCAST_ROWS:
        return components(links)
    return links.select("a", "b").coalesce(1).mapInArrow(run, "node long, root long")


def ends_of(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.explode(F.array("a", "b")).alias("s_node")).distinct()


_FILED = "key long, node long, root long, size int, at int"


_MET = "a long, b long, key long, root long, size int, at int, cell int, block int"


def _whole_keys(batches, settle):
    """``settle`` of the columns of whole keys (the first column, sorted) at a time."""
    waiting, held, rows = [], None, 0
    for b in batches:
        if not b.num_rows:
            continue
        waiting.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
        rows += b.num_rows
        if held and rows < len(held[0]):  # a long key is looked at a few times only
            continue
        held = [np.concatenate(c) for c in zip(*([held] if held else []), *waiting, strict=True)]
        waiting, rows = [], 0
        if cut := int(np.searchsorted(held[0], held[0][-1])):  # the last key may go on
            yield from settle(*(c[:cut] for c in held))
            held = [c[cut:] for c in held]
    if held:
        yield from settle(*(np.concatenate(c) for c in zip(held, *waiting, strict=True)))


def _ends(new: np.ndarray) -> np.ndarray:
    """For each row the end of its run; ``new`` tells where runs begin."""
    at = np.flatnonzero(new)
    return np.r_[at[1:], len(new)][np.cumsum(new) - 1]


def _partners(begin: np.ndarray, many: np.ndarray):
    """Index pairs (i, j) of every row i and the ``many`` rows from ``begin``, about ``HELD`` at a time."""
    total = np.cumsum(many)
    low = 0
    while low < len(many):
        high = max(low + 1, int(np.searchsorted(total, (total[low - 1] if low else 0) + HELD, "right")))
        n = many[low:high]
        i = np.repeat(np.arange(low, high), n)
        yield i, begin[i] + np.arange(len(i)) - np.repeat(np.cumsum(n) - n, n)
        low = high


def _may_reach(i: np.ndarray, j: np.ndarray, size: np.ndarray, at: np.ndarray, level: int, similarity: float) -> np.ndarray:
    """Of pairs that share a key: whether sizes and what can follow the key's last shingle allow the similarity."""
    x, y = size[i].astype(np.int64), size[j].astype(np.int64)
    reach = level + np.minimum(x - at[i], y - at[j])
    return (np.minimum(x, y) >= similarity * np.maximum(x, y) - 1e-6) & (reach >= similarity / (1 + similarity) * (x + y) - 1e-6)


def _sorted_pairs(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], 1), axis=0)


def meeting(filed: DataFrame, level: int, similarity: float, star: bool) -> DataFrame:
    """From nodes filed under keys (``_FILED``; ``at`` is the place of the key's last shingle in the set, ``level`` shingles are shared
    before it): a, b of pairs of different roots, with key null; every member of a key of more pairs as a, once for each cell in which
    it is to be compared; and every member of a crowded key as a, with cell null. With ``star`` keys are crowded early, and members of
    crowded keys also pair with one of them."""
    few, most = min(FEW, PAIRS), min(STAR, PAIRS) if star else PAIRS if level < LEVELS else np.inf

    def settle(key, node, root, size, at):
        """Whole keys, sorted by key and root."""
        import pyarrow as pa

        n = len(key)
        new_key = np.r_[True, key[1:] != key[:-1]]
        key_at, key_end = np.flatnonzero(new_key)[np.cumsum(new_key) - 1], _ends(new_key)
        run_end = _ends(new_key | np.r_[True, root[1:] != root[:-1]])
        after = key_end - run_end  # members of later roots
        made = np.add.reduceat(after, np.flatnonzero(new_key))[np.cumsum(new_key) - 1] / (key_end - key_at)  # pairs a member
        crowded = made > most
        found = [np.zeros((0, 2), np.int64)]
        for i, j in _partners(run_end, np.where(made <= few, after, 0)):
            good = _may_reach(i, j, size, at, level, similarity)
            found.append(_sorted_pairs(node[i[good]], node[j[good]]))
        if star:
            k = np.flatnonzero(crowded & (after < after[key_at]))
            good = _may_reach(key_at[k], k, size, at, level, similarity)
            found.append(_sorted_pairs(node[key_at[k[good]]], node[k[good]]))
        pairs, c = np.unique(np.concatenate(found), axis=0), np.flatnonzero(crowded)
        m = np.flatnonzero((made > few) & ~crowded)
        blocks, own = -(-(key_end - key_at)[m] // BLOCK), (np.arange(n) - key_at)[m] // BLOCK
        other = np.arange(blocks.sum()) - np.repeat(np.cumsum(blocks) - blocks, blocks)
        m, own = np.repeat(m, blocks), np.repeat(own, blocks)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32())
        names = ["a", "b", "key", "root", "size", "at", "cell", "block"]
        for rows, columns in (
            (len(pairs), {"a": pairs[:, 0], "b": pairs[:, 1]}),
            (len(c), {"a": node[c], "key": key[c], "root": root[c], "size": size[c], "at": at[c]}),
            (len(m), {"a": node[m], "key": key[m], "root": root[m], "size": size[m], "at": at[m], "cell": (np.minimum(own, other) << 15) + np.maximum(own, other), "block": own > other}),
        ):
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(columns[x].astype(k.to_pandas_dtype())) if x in columns else pa.nulls(rows, k) for x, k in zip(names, kinds, strict=True)], names=names)

    run = lambda batches: _whole_keys(batches, settle)
    return filed.repartition("key").sortWithinPartitions("key", "root", "node").mapInArrow(run, _MET)


def compared(members: DataFrame, nodes: DataFrame, level: int, similarity: float) -> DataFrame:
    """a, b of pairs of different roots in a cell whose parities allow the similarity."""

    def settle(key, cell, block, root, node, size, at, bits):
        """Whole keys, sorted by key, cell, block and root."""
        import pyarrow as pa

        new_cell = np.r_[True, (key[1:] != key[:-1]) | (cell[1:] != cell[:-1])]
        new_block = new_cell | np.r_[True, block[1:] != block[:-1]]
        new_run = new_block | np.r_[True, root[1:] != root[:-1]]
        begin = np.where(cell >> 15 == cell & 0x7FFF, _ends(new_run), _ends(new_block))  # blocks of a cell meet each other, or one itself
        least = PARITIES // 8
        narrow = np.zeros((len(key), least // 8), np.uint64)
        long = np.array([len(x) for x in bits], np.int64)
        for width in set(long.tolist()):
            k = np.flatnonzero(long == width)
            narrow[k] = np.bitwise_xor.reduce(np.frombuffer(b"".join(bits[k]), np.uint8).reshape(len(k), -1, least), 1).view(np.uint64)
        for i, j in _partners(begin, _ends(new_cell) - begin):
            good = (root[i] != root[j]) & _may_reach(i, j, size, at, level, similarity)
            i, j = i[good], j[good]
            far = (size[i].astype(np.int64) + size[j]) * ((1 - similarity) / (1 + similarity)) + 1e-6
            good = np.bitwise_count(narrow[i] ^ narrow[j]).sum(1, dtype=np.int64) <= far
            i, j, far = i[good], j[good], far[good]
            good = differing(bits[i].tolist(), bits[j].tolist()) <= far
            pairs = _sorted_pairs(node[i[good]], node[j[good]])
            if len(pairs):
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

    run = lambda batches: _whole_keys(batches, settle)
    told = nodes.select(F.col("s_node").alias("a"), F.when(F.length("s_wide") > F.length("s_odd"), F.col("s_wide")).otherwise(F.col("s_odd")).alias("bits"))
    rows = members.join(told, "a").select("key", "cell", "block", "root", F.col("a").alias("node"), "size", "at", "bits")
    return rows.repartition("key", "cell").sortWithinPartitions("key", "cell", "block", "root", "node").mapInArrow(run, "a long, b long")


def first_filed(nodes: DataFrame, roots: DataFrame) -> DataFrame:
    """Nodes under each shingle of ``s_first``."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for i in range(0, b.num_rows, 1024):
                part = b.slice(i, 1024)
                first = part.column(3).to_pylist()
                many = np.array([len(x) // 8 for x in first], np.int64)
                at = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                own = [pa.array(np.repeat(part.column(c).to_numpy(), many)) for c in range(3)]
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(b"".join(first), np.int64)), *own, pa.array(at.astype(np.int32))], names=["key", "node", "root", "size", "at"])

    rooted = nodes.join(small(roots), nodes["s_node"] == roots["node"], "left")
    return rooted.filter("s_size > 0").select("s_node", F.coalesce("root", "s_node").alias("root"), "s_size", "s_first").mapInArrow(run, _FILED)


def deeper_filed(crowded: DataFrame, sets: DataFrame, level: int, common: tuple, similarity: float) -> DataFrame:
    """Nodes under a crowded key and one more shingle of theirs behind it."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for r in b.to_pylist():
                s = in_order(np.frombuffer(r["s_set"], np.uint64), common)
                end = len(s) - least_shared(len(s), similarity) + level + 1
                for x in r["x"]:
                    at = np.arange(x["at"] + 1, min(end, len(s)), dtype=np.int32)
                    key = _mixed(s[at] ^ np.array([x["key"]], np.int64).view(np.uint64), 0x9E3779B97F4A7C15).view(np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(key), *[pa.array(np.full(len(at), v, k)) for v, k in ((r["node"], np.int64), (r["root"], np.int64), (len(s), np.int32))], pa.array(at)], names=["key", "node", "root", "size", "at"])

    by_node = crowded.groupBy("node").agg(F.first("root").alias("root"), F.collect_list(F.struct("key", "at")).alias("x"))
    return by_node.join(sets.withColumnRenamed("s_node", "node"), "node").select("node", "root", "x", "s_set").mapInArrow(run, _FILED)


def thinned(pairs: DataFrame, nodes: DataFrame, similarity: float, parity: str) -> DataFrame:
    """Pairs without those whose parities forbid the similarity."""
    side = lambda k: nodes.select(F.col("s_node").alias(k), F.col(parity).alias(f"o{k}"), F.col("s_size").alias(f"n{k}"))

    def check(batches):
        import pyarrow as pa

        for b in batches:
            most = b.column(4).to_numpy() * ((1 - similarity) / (1 + similarity)) + 1e-6
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(differing(b.column(2).to_pylist(), b.column(3).to_pylist()) <= most))

    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "oa", "ob", (F.col("na") + F.col("nb")).alias("n")).mapInArrow(check, "a long, b long")


def no_roots(spark) -> DataFrame:
    return spark.createDataFrame([], "node long, root long")


def classes(docs: DataFrame, similarity: float = SIMILARITY) -> tuple[DataFrame, DataFrame]:
    """Rows (doc_id, s_node), and s_node and root of every node that has links."""
    spark = docs.sparkSession
    common = common_shingles(docs)
    told = ("s_print", "s_size", "s_odd", "s_wide", "s_first")
    wide = stash(with_node(docs, ["doc_id"], *told, common=common, similarity=similarity), "prints")
    nodes = stash(wide.groupBy("s_node").agg(F.first(F.struct(*told)).alias("x"), F.min("doc_id").alias("doc_id")).select("s_node", "x.*", "doc_id"), "nodes")
    rows = stash(wide.select("doc_id", "s_node"), "rows")
    discard(wide)
    pairs = stash(candidates(nodes), "pairs")
    sets = sets_of(docs, nodes, ends_of(pairs))
    links, roots, left, most = None, None, pairs, 1
    while not left.isEmpty():
        both = left.select(F.explode(F.array(F.struct(F.col("a").alias("n"), "a", "b", "d"), F.struct(F.col("b").alias("n"), "a", "b", "d"))).alias("x")).select("x.*")
        turn = F.row_number().over(Window.partitionBy("n").orderBy("d", "a", "b"))
        picked = stash(both.withColumn("k", turn).filter(F.col("k") <= most).select("a", "b").distinct(), "picked")
        good = verified(picked, sets, similarity)
        links = stash(good if links is None else links.union(good), "links")
        roots = stash(joined(links), "roots")
        side = lambda k: roots.select(F.col("node").alias(k), F.col("root").alias(f"r{k}"))  # noqa: B023, E731
        rest = left.join(picked, ["a", "b"], "left_anti").join(side("a"), "a", "left").join(side("b"), "b", "left")
        left = stash(rest.filter("coalesce(ra, a) != coalesce(rb, b)").select("a", "b", "d"), "left")
        most *= 4
    discard(sets)
    release(spark)
    roots = exact_rest(docs, nodes, links, no_roots(spark) if roots is None else roots, common, similarity)
    return rows.select("doc_id", "s_node"), roots.select(F.col("node").alias("s_node"), "root")


def exact_rest(docs: DataFrame, nodes: DataFrame, links: DataFrame | None, roots: DataFrame, common: tuple, similarity: float) -> DataFrame:
    """``roots`` (node, root) after all links that are missing among ``links``."""
    filed, level = first_filed(nodes, roots), 0
    while True:
        for star in (True, False):  # crowded keys are looked at again once their groups are joined
            met = stash(meeting(filed, level, similarity, star), "met")
            release(docs.sparkSession)
            pairs = stash(thinned(met.filter("key IS NULL").select("a", "b").distinct(), nodes, similarity, "s_odd"), "thinned")
            near = thinned(pairs, nodes, similarity, "s_wide").union(compared(met.filter("cell IS NOT NULL"), nodes, level, similarity))
            pairs = stash(near.distinct(), "thinned")
            if not pairs.isEmpty():
                sets = sets_of(docs, nodes, ends_of(pairs))
                good = verified(pairs, sets, similarity)
                links = stash(good if links is None else links.union(good), "links")
                discard(sets)
                roots = stash(joined(links), "roots")
            crowded = met.filter("key IS NOT NULL AND cell IS NULL").select("key", F.col("a").alias("node"), "size", "at")
            if crowded.isEmpty():
                return roots
            filed = crowded.join(roots, "node", "left").select("key", "node", F.coalesce("root", "node").alias("root"), "size", "at")
        crowded = stash(filed, "crowded")
        sets = sets_of(docs, nodes, crowded.select(F.col("node").alias("s_node")).distinct())
        level += 1
        filed = deeper_filed(crowded, sets, level, common, similarity)


def one_of_each(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of ``docs`` without near copies: of each group linked by a Jaccard of ``similarity`` or more the one with the smallest
    doc_id stays (null ids come last, and of repeated rows one stays)."""
    rows, roots = classes(docs, similarity)
    named = rows.join(roots, "s_node", "left").select("doc_id", F.col("s_node").alias("node"), F.coalesce("root", "s_node").alias("root"))
    return first_of_each(docs, named, with_node, "s_node")
