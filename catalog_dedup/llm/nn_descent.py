"""Approximate nearest neighbours (largest inner product): an NN-descent graph, searched greedily.

Equal vectors are one node. To start the graph, nodes are dealt several times to the cell of their nearest seed, with other seeds
each time (cells above ``LEAF`` are split by hash), and the ``START`` best of the exact neighbours within a cell enter. Cells hold
about four times the square root of all nodes, LEAF at most, and deals grow with the logarithm of the number of cells, so that every size of input
is worked on alike.

In each round of NN-descent a node hands on its best ``SAMPLE`` edges that are new, and as many old ones drawn anew each round;
the same number of reversed edges of either kind is drawn by hash. They tell every node of which centres it is a member. Members of centres without
a new one stay at home; the vectors of others meet at blocks of about ``MEET`` centres, a row per node and block and so 4 * SAMPLE
rows of a node at most whatever the number of nodes. Pairs of members of one centre are compared if one of the two edges is new,
and better neighbours are joined back to their nodes. A centre and a block propose a node at most ``DEGREE`` distinct neighbours,
the best; as a node keeps no more, this loses none. An edge counts as new until it has been handed on. Rounds end when few edges
change, however many it takes: edges only get better, so they do end.

A query starts at its own node or, if it has none, at the first nodes of some blocks, keeps a pool of the best nodes (``POOL`` for
each doubling of the number of nodes) and in every round expands its best ``EXPAND`` unexpanded ones by a join with the graph; scores are exact inner products of the original
vectors in double precision. It stops when no pool has an unexpanded node, which comes to pass as a node is expanded once at most.

To build the graph, vectors get one more component that makes all of them equally long, so that the angle between them
orders as the inner product does. Vectors that are null, zero, of another length than the most common, or that hold null or
non-finite components take no part; neither do rows with a null id. Of rows with one id and different vectors each counts, rows
that repeat an id and a vector count once.
Ties go to the smaller vec_id. Extra columns are ignored, whatever their names. An empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import stash

BLOCK, MEET = 2048, 256
LEAF, START = 2048, 12
#: Seeds of all deals, at most; every task holds them.
MOST_SEEDS = 65_536
DEGREE, SAMPLE = 32, 16
#: Share of edges that changed below which the graph is done.
SETTLED = 0.01
POOL, EXPAND = 24, 96


def usable(table: DataFrame) -> DataFrame:
    """vec_id and vector (array<double>) of the rows that take part."""
    v = F.col("embedding").cast("array<double>")
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = table.select("vec_id", v.alias("vector")).filter(F.col("vec_id").isNotNull() & F.col("vector").isNotNull() & fine)
    size = rows.groupBy(F.size("vector").alias("n")).agg(F.count("*").alias("c")).orderBy(F.desc("c"), "n").first()
    return rows.filter(F.size("vector") == (size["n"] if size else 0))


def deals_for(count: int) -> tuple[int, int]:
    """How often nodes are dealt, and to how many cells."""
    cells = max(1, math.ceil(count / min(LEAF, 4 * math.sqrt(max(count, 1)))))
    deals = 2 + 2 * math.ceil(math.log2(cells))
    return deals, max(1, min(cells, MOST_SEEDS // deals))


def pool_for(count: int) -> int:
    return POOL * max(1, math.ceil(math.log2(max(count, 2))))


def block_of(node: Column, blocks: int, deal: int = 0) -> Column:
    return F.pmod(F.xxhash64(node, F.lit(deal)), F.lit(blocks)).cast("int")


def _matrix(column, kind) -> np.ndarray:
    rows = column.to_pylist()
    if not rows:
        return np.zeros((0, 0), np.float32 if kind == np.float16 else np.float64)
    return np.frombuffer(b"".join(rows), kind).reshape(len(rows), -1).astype(np.float32 if kind == np.float16 else np.float64)


def _lists(column):
    """(values, offsets) of a list column."""
    c = column.combine_chunks()
    return c.flatten().to_numpy(zero_copy_only=False), np.r_[0, np.cumsum(c.value_lengths().to_numpy(zero_copy_only=False))].astype(np.int64)


def _best(owner: np.ndarray, other: np.ndarray, score: np.ndarray, most: int) -> np.ndarray:
    """Positions of each owner's `most` best distinct others, by owner and falling score (ties: smaller other)."""
    order = np.lexsort((other, -score, owner))
    o, t = owner[order], other[order]
    again = np.r_[False, (o[1:] == o[:-1]) & (t[1:] == t[:-1])]  # equal pairs have equal scores, so they are adjacent
    order = order[~again]
    o = owner[order]
    first = np.r_[0, np.flatnonzero(o[1:] != o[:-1]) + 1] if len(o) else np.zeros(0, int)
    rank = np.arange(len(o)) - np.repeat(first, np.diff(np.r_[first, len(o)]))
    return order[rank < most]


_PROPOSED = "home int, us array<long>, nears array<long>, scores array<float>"


def _proposals(home: np.ndarray, own: np.ndarray, other: np.ndarray, score: np.ndarray):
    """An Arrow table with one row per home block and lists of (node, proposed neighbour, score)."""
    import pyarrow as pa

    order = np.argsort(home, kind="stable")
    home = home[order]
    first = np.r_[0, np.flatnonzero(home[1:] != home[:-1]) + 1, len(home)].astype(np.int32) if len(home) else np.zeros(1, np.int32)
    lists = [pa.ListArray.from_arrays(first, pa.array(x[order], t)) for x, t in ((own, pa.int64()), (other, pa.int64()), (score, pa.float32()))]
    return pa.table([pa.array(home[first[:-1]], pa.int32()), *lists], names=["home", "us", "nears", "scores"])


def start_graph(nodes: DataFrame, count: int) -> DataFrame:
    """The graph of the best exact neighbours within the cells of all deals."""
    deals, cells = deals_for(count)
    seeds = nodes.orderBy(F.xxhash64("node", F.lit("seed")), "node").limit(deals * cells).select("short").toArrow()
    seeds = _matrix(seeds.column("short"), np.float16)
    seeds = [seeds[np.arange(d, len(seeds), deals)] for d in range(deals)]

    def deal(batches):
        import pyarrow as pa

        for b in batches:
            if not b.num_rows:
                continue
            x = _matrix(b.column(2), np.float16)
            near = np.stack([(x @ c.T).argmax(1) if len(c) else np.zeros(len(x), np.int64) for c in seeds], 1).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, near.size + 1, deals), pa.int32()), pa.array(near.ravel()))
            yield pa.RecordBatch.from_arrays([*b.columns, lists], names=["block", "node", "short", "cells"])

    dealt = stash(nodes.select("block", "node", "short").mapInArrow(deal, "block int, node long, short binary, cells array<int>"), "dealt")
    each = dealt.select("block", "node", "short", F.posexplode("cells").alias("deal", "cell"))
    sizes = each.groupBy("deal", "cell").agg(F.ceil(F.count("*") / LEAF).cast("int").alias("parts"))  # a row a seed
    each = each.join(F.broadcast(sizes), ["deal", "cell"]).withColumn("part", F.pmod(F.xxhash64("node", "deal"), F.col("parts")).cast("int"))

    def exact(table):
        ids, home, x = table.column("node").to_numpy(), table.column("block").to_numpy(), _matrix(table.column("short"), np.float16)
        own, other, score = [], [], []
        k = min(START, len(ids) - 1)
        for i in range(0, len(ids), 512):
            s = x[i : i + 512] @ x.T
            s[np.arange(len(s)), np.arange(i, i + len(s))] = -np.inf
            top = np.argpartition(-s, k - 1, 1)[:, :k] if k else np.zeros((len(s), 0), int)
            own.append(np.repeat(np.arange(i, i + len(s)), k))
            other.append(ids[top].ravel())
            score.append(np.take_along_axis(s, top, 1).ravel())
        own, other, score = map(np.concatenate, (own, other, score))
        return _proposals(home[own], ids[own], other, score)

    found = each.select("deal", "cell", "part", "block", "node", "short").groupBy("deal", "cell", "part").applyInArrow(exact, _PROPOSED)
    empty = nodes.select("block", "node", F.array().cast("array<long>").alias("near"), F.array().cast("array<float>").alias("score"), F.array().cast("array<boolean>").alias("fresh"))
    return joined_back(empty, found, 0)


def members(graph: DataFrame, turn: int) -> DataFrame:
    """centre, member, fresh: both ends of the edges that the nodes hand on."""
    side = lambda c, new: graph.select("node", F.explode(c).alias("near"), F.lit(new).alias("fresh"))
    edges = side("new", True).union(side("old", False))
    drawn = Window.partitionBy("near", "fresh").orderBy(F.xxhash64("node", "near", F.lit(turn)), "node")
    turned = edges.withColumn("k", F.row_number().over(drawn)).filter(F.col("k") <= SAMPLE)
    return edges.select(F.col("node").alias("centre"), F.col("near").alias("member"), "fresh").union(turned.select(F.col("near").alias("centre"), F.col("node").alias("member"), "fresh"))


def descend(nodes: DataFrame, graph: DataFrame, count: int, turn: int) -> DataFrame:
    """One round: the graph after neighbours of neighbours have met, with ``changed`` new edges per node."""
    meets = max(1, -(-count // MEET))
    # A list per centre: 4 * SAMPLE members at most.
    moving = members(graph, turn).groupBy("centre").agg(F.collect_list(F.struct("member", "fresh")).alias("m")).filter(F.exists("m", lambda x: x["fresh"]))
    meet = moving.select("centre", F.explode("m").alias("x")).select("centre", "x.member", "x.fresh")
    meet = meet.groupBy("member", block_of(F.col("centre"), meets, 1).alias("at")).agg(F.collect_list("centre").alias("centres"), F.collect_list("fresh").alias("flags"))
    lookup = nodes.select("node", "short", F.col("block").alias("home")).join(graph.select(F.col("node").alias("w_node"), "worst"), F.col("node") == F.col("w_node")).select("node", "short", "home", "worst")
    sent = meet.join(lookup, F.col("member") == F.col("node")).select("at", "member", "short", "home", "worst", "centres", "flags")

    def compare(table):
        ids, home, x = table.column("member").to_numpy(), table.column("home").to_numpy(), _matrix(table.column("short"), np.float16)
        worst = table.column("worst").to_numpy(zero_copy_only=False)
        centres, offsets = _lists(table.column("centres"))
        flags, _ = _lists(table.column("flags"))
        row = np.repeat(np.arange(len(ids)), np.diff(offsets))
        order = np.lexsort((row, centres))
        c, r, f = centres[order], row[order], flags[order].astype(bool)
        bounds = np.r_[0, np.flatnonzero(c[1:] != c[:-1]) + 1, len(c)]
        own, other, score = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.float32)]
        for a, b in zip(bounds[:-1], bounds[1:], strict=True):
            # A member told by an edge and by a reversed one stands once; it is new if either is.
            m, at = np.unique(r[a:b], return_inverse=True)
            if len(m) < 2:
                continue
            new = np.zeros(len(m), bool)
            np.logical_or.at(new, at, f[a:b])
            s = x[m] @ x[m].T
            s[~(new[:, None] | new[None, :])] = -np.inf
            np.fill_diagonal(s, -np.inf)
            i, j = np.nonzero(s > worst[m][:, None])
            own.append(m[i])
            other.append(m[j])
            score.append(s[i, j])
        own, other, score = np.concatenate(own), ids[np.concatenate(other)], np.concatenate(score)
        at = _best(own, other, score, DEGREE)
        return _proposals(home[own[at]], ids[own[at]], other[at], score[at])

    return joined_back(graph.select("block", "node", "near", "score", "fresh"), sent.groupBy("at").applyInArrow(compare, _PROPOSED), turn)


_GRAPH = "block int, node long, near array<long>, score array<float>, fresh array<boolean>, new array<long>, old array<long>, worst float, changed int"


def joined_back(graph: DataFrame, found: DataFrame, turn: int) -> DataFrame:
    """The graph with the proposals ``found``: the best DEGREE of old and new edges of each node, with those that it hands on next
    (``new``, which count as old from then on, and ``old``), its worst score and how many edges changed."""

    def merge(table, proposed):
        import pyarrow as pa

        names = ("block", "node", "near", "score", "fresh", "new", "old", "worst", "changed")
        nodes = table.column("node").to_numpy() if table.num_rows else np.zeros(0, np.int64)
        n, by = len(nodes), np.argsort(nodes)
        near, ends = _lists(table.column("near"))
        score, fresh = _lists(table.column("score"))[0], _lists(table.column("fresh"))[0].astype(bool)
        us, nears, scores = (_lists(proposed.column(c))[0] for c in ("us", "nears", "scores"))
        own = np.r_[np.repeat(np.arange(n), np.diff(ends)), by[np.searchsorted(nodes[by], us)] if len(us) else np.zeros(0, int)]
        other, value, came = np.r_[near, nears].astype(np.int64), np.r_[score, scores].astype(np.float32), np.r_[np.zeros(len(near), bool), np.ones(len(us), bool)]
        fresh = np.r_[fresh, np.ones(len(us), bool)]
        order = np.lexsort((came, other, own))  # a known edge comes before the same one proposed
        order = order[np.r_[True, (own[order][1:] != own[order][:-1]) | (other[order][1:] != other[order][:-1])]] if len(order) else order
        own, other, value, fresh, came = (v[order] for v in (own, other, value, fresh, came))
        at = _best(own, other, value, DEGREE)
        own, other, value, fresh, came = (v[at] for v in (own, other, value, fresh, came))

        def first(chosen, key):
            """Of the chosen edges the SAMPLE first of each node by key."""
            e = np.flatnonzero(chosen)
            e = e[np.lexsort((key[e], own[e]))]
            heads = np.r_[0, np.flatnonzero(np.diff(own[e])) + 1] if len(e) else np.zeros(0, int)
            return e[np.arange(len(e)) - np.repeat(heads, np.diff(np.r_[heads, len(e)])) < SAMPLE]

        new = first(fresh, np.arange(len(own)))
        mixed = (nodes[own] * 31 + other + turn).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) if len(own) else np.zeros(0, np.uint64)
        old = first(~fresh, mixed ^ (mixed >> np.uint64(29)))
        fresh[new] = False
        size = np.bincount(own, minlength=n)
        worst = np.full(n, -np.inf, np.float32)
        np.minimum.at(low := np.full(n, np.inf, np.float32), own, value)
        worst[size >= DEGREE] = low[size >= DEGREE]
        column = lambda e, x, kind: pa.ListArray.from_arrays(np.r_[0, np.cumsum(np.bincount(own[e], minlength=n))].astype(np.int32), pa.array(x[e], kind))
        every = np.arange(len(own))
        lists = [column(every, other, pa.int64()), column(every, value, pa.float32()), column(every, fresh, pa.bool_()), column(new, other, pa.int64()), column(old, other, pa.int64())]
        block = table.column("block") if n else pa.array([], pa.int32())
        return pa.table([block, pa.array(nodes, pa.int64()), *lists, pa.array(worst), pa.array(np.bincount(own, came, n).astype(np.int32))], names=names)

    return graph.groupBy("block").cogroup(found.groupBy("home")).applyInArrow(merge, _GRAPH)


def build(nodes: DataFrame, count: int) -> DataFrame:
    """node and adjacent (its neighbours and the best of those it is a neighbour of)."""
    graph, turn, moving = stash(start_graph(nodes, count), "graph"), 0, True
    while moving:
        turn += 1
        graph = stash(descend(nodes, graph, count, turn), "graph")
        moving = (graph.agg(F.sum("changed")).first()[0] or 0) > SETTLED * DEGREE * count
    edges = graph.select("node", F.explode(F.arrays_zip("near", "score")).alias("e")).select("node", F.col("e.near").alias("near"), F.col("e.score").alias("score"))
    turned = edges.withColumn("k", F.row_number().over(Window.partitionBy("near").orderBy(F.desc("score"), "node"))).filter(F.col("k") <= 2 * DEGREE)
    both = edges.select("node", "near").union(turned.select(F.col("near").alias("node"), F.col("node").alias("near")))
    return stash(both.groupBy("node").agg(F.collect_set("near").alias("adjacent")), "adjacency")


def search(nodes: DataFrame, adjacency: DataFrame, queries: DataFrame, blocks: int, top: int, most: int) -> DataFrame:
    """q, node, score: the best nodes found for ``queries`` (q, vector, start: array of nodes), at least ``top`` where there are; pools hold ``most``."""
    stored = nodes.select("block", "node", "exact")

    def score_in_block(asked, table):
        import pyarrow as pa

        kinds = pa.schema([("q", pa.int64()), ("ids", pa.list_(pa.int64())), ("scores", pa.list_(pa.float64()))])
        if not asked.num_rows:
            return kinds.empty_table()
        ids = table.column("node").to_numpy()
        order = np.argsort(ids)
        x = _matrix(table.column("exact"), np.float64)[order]
        wanted, offsets = _lists(asked.column("wanted"))
        at = np.searchsorted(ids[order], wanted)
        qs, worst = _matrix(asked.column("vector"), np.float64), asked.column("worst").to_numpy(zero_copy_only=False)
        out_ids, out_scores = [], []
        for i in range(len(qs)):
            a, b = offsets[i], offsets[i + 1]
            s = x[at[a:b]] @ qs[i]
            good = s >= worst[i]
            out_ids.append(wanted[a:b][good])
            out_scores.append(s[good])
        return pa.table([asked.column("q"), pa.array(out_ids, pa.list_(pa.int64())), pa.array(out_scores, pa.list_(pa.float64()))], schema=kinds)

    def scored(asked: DataFrame) -> DataFrame:
        """asked: q, node -> q with lists of nodes and scores, those below the pool's worst left out."""
        by = asked.groupBy("q", block_of(F.col("node"), blocks).alias("block")).agg(F.collect_list("node").alias("wanted"))
        by = by.join(pool.select(F.col("q").alias("p_q"), "vector", F.when(F.size("scores") < most, F.lit(float("-inf"))).otherwise(F.array_min("scores")).alias("worst")), F.col("q") == F.col("p_q")).select("block", "q", "vector", "worst", "wanted")
        found = by.groupBy("block").cogroup(stored.groupBy("block")).applyInArrow(score_in_block, "q long, ids array<long>, scores array<double>")
        return found.groupBy(F.col("q").alias("f_q")).agg(F.flatten(F.collect_list("ids")).alias("more"), F.flatten(F.collect_list("scores")).alias("more_scores"))

    def merge(batches):
        import pyarrow as pa

        for b in batches:
            cols = {n: c.to_pylist() for n, c in zip(b.schema.names, b.columns, strict=True)}
            ids, scores, done, nxt = [], [], [], []
            for i0, s0, d0, x0, m, ms in zip(*[cols[n] for n in ("ids", "scores", "done", "next", "more", "more_scores")], strict=True):
                i1, s1 = np.array(i0 + (m or []), np.int64), np.array(s0 + (ms or []), float)
                d1 = np.r_[np.isin(np.array(i0, np.int64), np.array(x0, np.int64)) | np.array(d0, bool), np.zeros(len(i1) - len(i0), bool)]
                order = np.lexsort((~d1, i1))
                i1, s1, d1 = i1[order], s1[order], d1[order]
                keep = np.r_[True, i1[1:] != i1[:-1]] if len(i1) else np.zeros(0, bool)
                i1, s1, d1 = i1[keep], s1[keep], d1[keep]
                best = np.lexsort((i1, -s1))[:most]
                i1, s1, d1 = i1[best], s1[best], d1[best]
                ids.append(i1)
                scores.append(s1)
                done.append(d1)
                nxt.append(i1[~d1][:EXPAND])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(ids, pa.list_(pa.int64())), pa.array(scores, pa.list_(pa.float64())), pa.array(done, pa.list_(pa.bool_())), pa.array(nxt, pa.list_(pa.int64()))], names=["q", "vector", "ids", "scores", "done", "next"])

    schema = "q long, vector binary, ids array<long>, scores array<double>, done array<boolean>, next array<long>"
    none = lambda kind: F.array().cast(f"array<{kind}>")
    pool = queries.select("q", "vector", none("long").alias("ids"), none("double").alias("scores"), none("boolean").alias("done"), none("long").alias("next"))
    asked = queries.select("q", F.explode("start").alias("node"))
    hop = 0
    while True:
        if hop:
            ahead = pool.select("q", F.explode("next").alias("node")).join(adjacency, "node").select("q", F.explode("adjacent").alias("node")).distinct()
            known = pool.select("q", F.explode("ids").alias("node"))
            asked = ahead.join(known, ["q", "node"], "left_anti")
        found = scored(asked)
        pool = stash(pool.join(found, F.col("q") == F.col("f_q"), "left").select("q", "vector", "ids", "scores", "done", "next", "more", "more_scores").mapInArrow(merge, schema), "pool")
        if pool.filter(F.size("next") > 0).isEmpty():
            break
        hop += 1
    best = pool.select("q", F.explode(F.slice(F.arrays_zip("ids", "scores"), 1, top)).alias("x"))
    return best.select("q", F.col("x.ids").alias("node"), F.col("x.scores").alias("score"))


def neighbours(table: DataFrame, every: int = 20, top: int = 20) -> DataFrame:
    """query_id, rank, vec_id, score: the ``top`` nearest other rows found for each row whose vec_id is divisible by ``every``."""
    rows = stash(usable(table).distinct(), "vectors")
    groups = stash(rows.select("vector").distinct().withColumn("norm2", F.aggregate("vector", F.lit(0.0), lambda a, x: a + x * x)), "groups")
    numbered = stash(groups.withColumn("node", F.monotonically_increasing_id()), "numbered")
    stats = numbered.agg(F.count("*").alias("n"), F.max("norm2").alias("m")).first()
    count, longest = stats["n"], stats["m"] or 0.0
    blocks = max(1, -(-count // BLOCK))

    def pack(batches):
        import pyarrow as pa

        for b in batches:
            v = np.array(b.column(1).to_pylist(), float).reshape(b.num_rows, -1)
            rest = np.sqrt(np.maximum(longest - b.column(2).to_numpy(), 0.0))
            short = (np.c_[v, rest] / max(np.sqrt(longest), 1e-300)).astype(np.float16)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x.tobytes() for x in short]), pa.array([x.tobytes() for x in v])], names=["node", "short", "exact"])

    packed = numbered.select("node", "vector", "norm2").mapInArrow(pack, "node long, short binary, exact binary")
    nodes = stash(packed.withColumn("block", block_of(F.col("node"), blocks)), "blocks")
    adjacency = build(nodes, count)
    owners = stash(rows.join(numbered.select("node", "vector"), "vector").select("vec_id", "node"), "owners")
    asking = owners.filter(F.col("vec_id") % every == 0)
    queries = asking.select("node").distinct().join(nodes.select("node", "exact"), "node").select(F.col("node").alias("q"), F.col("exact").alias("vector"), F.array("node").alias("start"))
    found = stash(search(nodes, adjacency, stash(queries, "queries"), blocks, top + 1, max(pool_for(count), top + 1)), "found")
    # A node stands for its copies; the first top + 1 of them by id are enough.
    first = owners.withColumn("k", F.row_number().over(Window.partitionBy("node").orderBy("vec_id"))).filter(F.col("k") <= top + 1).drop("k")
    hits = asking.select(F.col("vec_id").alias("query_id"), F.col("node").alias("q")).join(found, "q").join(first, "node").filter("vec_id != query_id").select("query_id", "vec_id", "score").distinct()
    ranked = hits.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))).filter(F.col("rank") <= top)
    return ranked.select("query_id", "rank", "vec_id", "score")
