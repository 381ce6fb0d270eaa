"""SentencePiece encoding and decoding through a relational lattice.

Distinct units (see ``units``) are counted. For each, the substrings of at most the longest piece's length are exploded and
equi-joined to the piece table (a file of fixed size, broadcast); the edges are grouped by unit, which is how they are
partitioned already, and a higher-order aggregate folds the Viterbi recurrence over them. Units of over ``LONG`` characters are
exploded in blocks of ``STRIDE`` starts and their grouped edges folded block after block, so their length has no bound but the
16 bytes a character that the fold keeps.

The result is a dictionary from units, told apart by 96 hash bits, to ids. Documents are spelt from it in one pass: entries of
the most frequent units, at most ``HEAD`` of them, are files in the shared folder, sorted by hash, which every worker maps into
memory (so a host holds each page once, and only pages in use). Where units are left that are not in this head, a task writes
the ids of its documents to a file in the shared folder, with holes for those units, and names the distinct ones it lacks; they
are joined with the dictionary, and the holes of each file are filled from its own rows of that join. So nothing but rare units
is ever shuffled, and no text.

The pieces and scores of the file are read as a unigram lexicon whatever model it was made for: of a BPE file the ids are the
best path by its scores and not its merges. Scores add up along a path; of equally good paths the one with the longer last piece
wins. A character that is no piece becomes its UTF-8 bytes (or the unknown id where the table has no byte pieces). Null and empty
texts have no ids and decode to the empty text. Rows may repeat. Input columns named like a result are replaced, others keep
their names whatever they are. An empty table gives no rows.
"""

from __future__ import annotations

import uuid
from collections import Counter

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import carried, discard, open_store, others, release, shared_folder, stash
from .pieces import SPACE_MARK, PieceTable
from .units import Cutter, hashes, hashes_of, portions

LONG = 64
#: Starts of edges that a row of a long unit's lattice holds.
STRIDE = 256
#: Bound of the mapped part of the dictionary in entries (16 bytes and the ids each), entries in one of its files, and the bytes
#: of ids beyond which an entry stays out.
HEAD, SHELF, BULKY = 100_000_000, 200_000, 512
#: Units that a task counts before it hands them on.
COUNTED = 300_000


def distinct_units(docs: DataFrame, table: PieceTable) -> DataFrame:
    """word (a unit), n over all documents; tasks add up what they meet first."""

    def count(batches):
        import pyarrow as pa

        cutter, seen = Cutter(table), Counter()

        def give():
            units = list(seen)
            for i in range(0, len(units), 50_000):
                part = units[i : i + 50_000]
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.string()), pa.array([seen[u] for u in part], pa.int64())], names=["word", "n"])
            seen.clear()

        for b in batches:
            for i in range(0, b.num_rows, 1024):
                for codes, heads, _ in cutter.blocks(b.column(0).slice(i, 1024).to_pylist()):
                    _, at, times = np.unique(hashes(codes, heads)[0], return_index=True, return_counts=True)
                    text = codes.tobytes().decode("utf-32-le")
                    for x, y, n in zip(heads[at].tolist(), heads[at + 1].tolist(), times.tolist(), strict=True):
                        seen[text[x:y]] += n
                    if len(seen) > COUNTED:
                        yield from give()
        yield from give()

    return docs.select("text").mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


#: An edge of a unit of at most LONG characters in one long: end, start (11 bits each) and id + 1 (20 bits, 0 for an unknown character).
_END, _START, _MASK = 31, 20, (1 << 11) - 1


def piece_rows(spark, table: PieceTable) -> DataFrame:
    """known, code (id + 1), score and a long as the key, which makes the lookup cheaper; the text itself decides."""
    return F.broadcast(spark.createDataFrame([(p, i + 1, float(s)) for p, (i, s) in table.pieces.items()], "known string, code long, score double").withColumn("key", F.xxhash64("known")))


def edges(words: DataFrame, table: PieceTable, parts: int) -> DataFrame:
    """wid and its lattice: (e, s) with the packed edge and its score, by end and start.

    Everything happens within the partitions of ``wid``: exploding and the broadcast join keep them, so grouping needs no shuffle.
    """
    starts = words.repartition(parts, "wid").select("wid", "word", F.explode(F.sequence(F.lit(1), F.length("word"))).alias("start"))
    subs = starts.select("wid", "word", "start", F.explode(F.sequence(F.lit(1), F.least(F.lit(table.longest), F.length("word") - F.col("start") + 1))).alias("n"))
    pieces = subs.select("wid", "start", "n", F.substring("word", F.col("start"), F.col("n")).alias("piece"))
    hits = pieces.join(piece_rows(words.sparkSession, table), F.xxhash64("piece") == F.col("key"), "left").filter("piece = known OR n = 1")
    own = lambda c, other: F.when(F.col("piece") == F.col("known"), F.col(c)).otherwise(F.lit(other))
    from_ = F.col("start").cast("long") - 1
    packed = F.shiftleft(from_ + F.col("n"), _END).bitwiseOR(F.shiftleft(from_, _START)).bitwiseOR(own("code", 0).cast("long"))
    return hits.select("wid", F.struct(packed.alias("e"), own("score", table.unknown).alias("s")).alias("x")).groupBy("wid").agg(F.sort_array(F.collect_list("x")).alias("edges"))


def _end(e: Column) -> Column:
    return F.shiftright(e, _END).cast("int")


def _start(e: Column) -> Column:
    return F.shiftright(e, _START).bitwiseAND(_MASK).cast("int")


def viterbi(lattice: Column) -> Column:
    """For each position the packed last edge of the best path to it. Edges come by end, then start."""
    empty = F.array().cast("array<struct<score: double, edge: bigint>>")

    def step(best, x):
        reached = lambda: x["s"] + F.coalesce(F.get(best, _start(x["e"]) - 1)["score"], F.lit(0.0))
        last = lambda: F.array(F.struct(reached().alias("score"), x["e"].alias("edge")))
        size = F.size(best)
        return F.when(size < _end(x["e"]), F.concat(best, last())).when(reached() > F.get(best, size - 1)["score"], F.concat(F.slice(best, F.lit(1), size - 1), last())).otherwise(best)

    return F.transform(F.aggregate(lattice, empty, step), lambda y: y["edge"])


def path(last: Column, word: Column, table: PieceTable) -> Column:
    """The ids along the best path, unknown characters spelt."""
    start = F.struct(F.size(last).alias("at"), F.array().cast("array<bigint>").alias("way"))

    def back(state, i):
        e = F.get(last, i - 1)
        return F.when(state["at"] == i, F.struct(_start(e).alias("at"), F.concat(F.array(e), state["way"]).alias("way"))).otherwise(state)

    way = F.aggregate(F.reverse(F.sequence(F.lit(1), F.size(last))), start, back)["way"]
    code = lambda e: e.bitwiseAND((1 << 20) - 1).cast("int") - 1
    text = lambda e: F.hex(F.encode(F.substring(word, _start(e) + 1, F.lit(1)), "UTF-8"))
    spelt = (lambda e: F.transform(F.sequence(F.lit(0), (F.length(text(e)) / 2).cast("int") - 1), lambda k: F.conv(F.substring(text(e), 2 * k + 1, F.lit(2)), 16, 10).cast("int") + table.bytes_from)) if table.bytes_from >= 0 else (lambda e: F.array(F.lit(table.unknown_id)))
    return F.flatten(F.transform(way, lambda e: F.when(code(e) >= 0, F.array(code(e))).otherwise(spelt(e))))


def id_type(table: PieceTable) -> np.dtype:
    """The narrowest type that holds every id and one value more."""
    most = max([table.unknown_id, table.bytes_from + 255, *(i for i, _ in table.pieces.values())])
    return np.dtype("<u2" if most < 0xFFFF else "<u4")


def spell_unknown(c: str, table: PieceTable) -> list[int]:
    return [table.bytes_from + v for v in c.encode("utf-8")] if table.bytes_from >= 0 else [table.unknown_id]


def long_units(units: DataFrame, table: PieceTable) -> DataFrame:
    """n, h, k and code of units of over LONG characters: their edges by blocks of STRIDE starts, folded one block after the other."""

    def cut(batches):
        """A row per block: its number, how many edges' starts are its own, and its characters with those that its last pieces reach."""
        import pyarrow as pa

        kinds = pa.schema([("n", pa.int64()), ("h", pa.int64()), ("k", pa.int64()), ("block", pa.int32()), ("own", pa.int32()), ("word", pa.string())])
        for b in batches:
            for word, n in zip(*[c.to_pylist() for c in b.columns], strict=True):
                h, k = hashes_of([word])
                h, k = int(h.view(np.int64)[0]), int(k[0])
                for first in range(0, len(word), STRIDE * 256):
                    at = range(first, min(len(word), first + STRIDE * 256), STRIDE)
                    yield pa.RecordBatch.from_pylist([{"n": n, "h": h, "k": k, "block": a // STRIDE, "own": min(STRIDE, len(word) - a), "word": word[a : a + STRIDE + table.longest - 1]} for a in at], schema=kinds)

    blocks = units.select("word", "n").mapInArrow(cut, "n long, h long, k long, block int, own int, word string")
    key = ["n", "h", "k", "block"]
    starts = blocks.repartition("h", "k", "block").select(*key, "word", F.explode(F.sequence(F.lit(1), F.col("own"))).alias("start"))
    subs = starts.select(*key, "start", F.explode(F.sequence(F.lit(1), F.least(F.lit(table.longest), F.length("word") - F.col("start") + 1))).alias("size"), "word")
    pieces = subs.select(*key, "start", "size", F.substring("word", F.col("start"), F.col("size")).alias("piece"))
    hits = pieces.join(piece_rows(units.sparkSession, table), F.xxhash64("piece") == F.col("key"), "left").filter("piece = known OR size = 1")
    found = F.col("piece") == F.col("known")
    edge = F.struct((F.col("start") - 1).alias("start"), "size", F.when(found, F.col("code") - 1).otherwise(-1).alias("id"), F.when(found, F.col("score")).otherwise(F.lit(table.unknown)).alias("score"), F.when(~found | F.col("known").isNull(), F.col("piece")).alias("c"))
    lattice = hits.groupBy(*key).agg(F.sort_array(F.collect_list(edge)).alias("edges")).repartition("h", "k").sortWithinPartitions("h", "k", "block")
    kind = id_type(table)

    def fold(batches):
        import pyarrow as pa

        kinds = pa.schema([("n", pa.int64()), ("h", pa.int64()), ("k", pa.int64()), ("code", pa.binary())])
        key, score, last, odd = None, [], [], {}

        def done():
            out, at = [], len(last) - 1
            while at:
                size, i = last[at]
                at -= size
                out.append([i] if i >= 0 else spell_unknown(odd[at], table))
            return pa.RecordBatch.from_pylist([{"n": key[0], "h": key[1], "k": key[2], "code": np.array([i for part in reversed(out) for i in part], kind).tobytes()}], schema=kinds)

        for b in batches:
            for j in range(b.num_rows):
                n, h, k, block, found = (c[j].as_py() for c in b.columns)
                if key != (n, h, k):
                    if key:
                        yield done()
                    key, score, last, odd = (n, h, k), [0.0], [(0, 0)], {}
                for e in found:  # by start: a start's score is final when its edges are met
                    a = block * STRIDE + e["start"]
                    z = a + e["size"]
                    while len(score) <= z:
                        score.append(-np.inf)
                        last.append((0, 0))
                    if score[a] + e["score"] > score[z]:
                        score[z], last[z] = score[a] + e["score"], (e["size"], e["id"])
                    if e["id"] < 0:
                        odd[a] = e["c"]
        if key:
            yield done()

    return lattice.mapInArrow(fold, "n long, h long, k long, code binary")


def dictionary(docs: DataFrame, table: PieceTable) -> DataFrame:
    """n, h and k (hashes) and code (ids as bytes) of every distinct unit, written to the shared folder."""
    words = stash(distinct_units(docs, table).withColumn("wid", F.monotonically_increasing_id()), "units")
    release(docs.sparkSession)
    kind = id_type(table)
    parts = max(12, words.count() // 40_000)
    short, long = words.filter(F.length("word") <= LONG), words.filter(F.length("word") > LONG)
    best = edges(short, table, parts).select("wid", viterbi(F.col("edges")).alias("last"))
    best = best.join(short.repartition(parts, "wid").hint("shuffle_hash"), "wid").select("word", "n", path(F.col("last"), F.col("word"), table).alias("ids"))

    def pack(batches):
        import pyarrow as pa

        for b in batches:
            if not b.num_rows:
                continue
            ids = b.column(2)
            flat = pa.py_buffer(ids.flatten().to_numpy(zero_copy_only=False).astype(kind).tobytes())
            ends = np.r_[0, np.cumsum(ids.value_lengths().to_numpy(zero_copy_only=False))] * kind.itemsize
            h, k = hashes_of(b.column(0).to_pylist())
            code = pa.Array.from_buffers(pa.binary(), b.num_rows, [None, pa.py_buffer(ends.astype(np.int32)), flat])
            yield pa.RecordBatch.from_arrays([b.column(1), pa.array(h.view(np.int64)), pa.array(k.astype(np.int64)), code], names=["n", "h", "k", "code"])

    made = best.mapInArrow(pack, "n long, h long, k long, code binary")
    made = stash(made if long.isEmpty() else made.union(long_units(long, table)), "dictionary")
    discard(words)
    return made


def stretches(begins: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """begin, begin + 1, ... of each stretch, one after the other."""
    ends = np.cumsum(sizes)
    return np.repeat(begins - ends + sizes, sizes) + np.arange(ends[-1] if len(ends) else 0)


class Head:
    """The mapped part of the dictionary. A file (shelf) holds the entries whose first hash begins with its number: offsets of
    buckets by the bits that follow, the hashes in order, where ids start, and the ids one after the other."""

    def __init__(self, paths: list[str | None], kind: np.dtype):
        self.kind, self.bits = kind, (len(paths) - 1).bit_length()
        self.shelves = [self.open(p) if p else None for p in paths]

    @staticmethod
    def shelf(first: np.ndarray, second: np.ndarray, starts: np.ndarray, ids: np.ndarray, bits: int) -> bytes:
        """The file of entries in the order of their first hash."""
        more = max(1, len(first).bit_length())
        buckets = np.searchsorted(((first << np.uint64(bits)) >> np.uint64(64 - more)).astype(np.int64), np.arange((1 << more) + 1))
        return b"".join([np.array([len(first), more], np.int64).tobytes(), first.tobytes(), buckets.astype(np.uint32).tobytes(), second.tobytes(), starts.astype(np.uint32).tobytes(), ids.tobytes()])

    def open(self, path: str) -> tuple:
        data = np.memmap(mapped(path), np.uint8, "r")
        n, more = data[:16].view(np.int64).tolist()
        ends = np.cumsum([16, 8 * n, 4 * ((1 << more) + 1), 4 * n, 4 * (n + 1)]).tolist()
        kinds = (np.uint64, np.uint32, np.uint32, np.uint32)
        return more, *(data[a:b].view(k) for a, b, k in zip(ends[:-1], ends[1:], kinds, strict=True)), data[ends[-1] :].view(self.kind)

    def find(self, shelf: tuple, first: np.ndarray, second: np.ndarray) -> np.ndarray:
        """Positions of the entries of units of one shelf, -1 where there is none."""
        more, known, buckets, others_, _, _ = shelf
        out = np.full(len(first), -1, np.int64)
        bucket = ((first << np.uint64(self.bits)) >> np.uint64(64 - more)).astype(np.int64)
        at, end = buckets[bucket].astype(np.int64), buckets[bucket + 1].astype(np.int64)
        rest = np.flatnonzero(at < end)
        while len(rest):
            p = at[rest]
            hit = (known[p] == first[rest]) & (others_[p] == second[rest])
            out[rest[hit]] = p[hit]
            rest = rest[~hit]
            at[rest] += 1
            rest = rest[at[rest] < end[rest]]
        return out

    def spell(self, first: np.ndarray, second: np.ndarray, hole: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The ids of all units one after the other, the number of each unit's, and which units are missing (a hole each)."""
        number = (first >> np.uint64(64 - self.bits)).astype(np.int64) if self.bits else np.zeros(len(first), np.int64)
        order, sizes, missing, found = np.argsort(number, kind="stable"), np.ones(len(first), np.int64), [], []
        ends = np.cumsum(np.bincount(number, minlength=len(self.shelves))).tolist()
        for shelf, a, b in zip(self.shelves, [0, *ends[:-1]], ends, strict=True):
            if b == a:
                continue
            at = order[a:b]
            p = self.find(shelf, first[at], second[at]) if shelf else np.full(b - a, -1)
            missing.append(at[p < 0])
            at, p = at[p >= 0], p[p >= 0]
            if len(at):
                begins = shelf[4][p].astype(np.int64)
                sizes[at] = shelf[4][p + 1] - begins
                found.append((shelf[5], at, begins))
        starts = np.cumsum(sizes) - sizes
        out = np.full(int(sizes.sum()), hole, self.kind)
        for ids, at, begins in found:
            out[stretches(starts[at], sizes[at])] = ids[stretches(begins, sizes[at])]
        return out, sizes, np.sort(np.concatenate([np.zeros(0, np.int64), *missing]))


def mapped(uri: str) -> str:
    """A local path of a file in the shared folder: the file itself where the folder is mounted, else the executor's copy."""
    from pyspark import SparkFiles

    return uri.removeprefix("file://").removeprefix("file:") if uri.startswith(("file:", "/")) else SparkFiles.get(uri.rsplit("/", 1)[1])


def head_of(entries: DataFrame, kind: np.dtype) -> tuple[list[str | None], Column]:
    """Writes the most frequent entries, HEAD at most, to files in the shared folder; returns their paths by the upper bits of the
    hash, and the condition of the entries left out.

    Entries enter by steps of a sixteenth of a doubling in frequency, so nothing is sorted as a whole."""
    spark = entries.sparkSession
    step, usual = F.floor(F.log2("n") * 16).cast("int"), F.length("code") <= BULKY
    steps = entries.filter(usual).groupBy(step.alias("step")).agg(F.count("*").alias("rows")).orderBy(F.desc("step")).collect()  # a few hundred at most
    least, rows = 1 << 30, 0
    for r in steps:
        if rows + r["rows"] > HEAD:
            break
        least, rows = r["step"], rows + r["rows"]
    inside, bits = usual & (step >= least), (rows // SHELF).bit_length()
    folder = f"{shared_folder(spark)}/head-{uuid.uuid4().hex}"
    shelf = F.shiftrightunsigned("h", 64 - bits).cast("int") if bits else F.lit(0)

    def write(batches):
        import pyarrow as pa

        store, top = open_store(folder)
        store.create_dir(top, recursive=True)
        batches = list(batches)  # SHELF entries or few times as many
        if not batches:
            return
        table = pa.Table.from_batches(batches)
        numbers = table.column("shelf").to_numpy()
        for n in np.unique(numbers).tolist():
            part = table.filter(pa.array(numbers == n))
            first, second = part.column("h").to_numpy().view(np.uint64), part.column("k").to_numpy().astype(np.uint32)
            order = np.argsort(first)
            codes = pa.concat_arrays(part.column("code").chunks).take(pa.array(order)).to_pylist()
            starts = np.r_[0, np.cumsum(list(map(len, codes)))] // kind.itemsize
            name = f"{n}-{uuid.uuid4().hex}.shelf"
            with store.open_output_stream(f"{top}/{name}") as sink:
                sink.write(Head.shelf(first[order], second[order], starts, np.frombuffer(b"".join(codes), kind), bits))
            yield pa.RecordBatch.from_pylist([{"shelf": n, "name": name}], schema=pa.schema([("shelf", pa.int32()), ("name", pa.string())]))

    shelves = entries.filter(inside).select(shelf.alias("shelf"), "h", "k", "code").repartition(1 << bits, "shelf").mapInArrow(write, "shelf int, name string").collect()  # a row a file
    paths: list[str | None] = [None] * (1 << bits)
    for r in shelves:
        paths[r["shelf"]] = f"{folder}/{r['name']}"
        if not folder.startswith(("file:", "/")):
            spark.sparkContext.addFile(paths[r["shelf"]])
    return paths, ~inside


def digest(text: bytes) -> bytes:
    from xxhash import xxh3_128_digest

    return xxh3_128_digest(text)


def encode(docs: DataFrame, table: PieceTable, keep: list[str], check: bool = True) -> DataFrame:
    """``keep`` columns, ``n_tokens``, ``ids`` and, with ``check``, ``round_trip`` (the ids decode to the text) of every row."""
    spark, kind = docs.sparkSession, id_type(table)
    entries = dictionary(docs, table)
    paths, beyond = head_of(entries, kind)
    release(spark)
    keep = others(keep, ["n_tokens", "ids", "round_trip"])
    rows = docs.select(carried(keep).alias("row"), "text")
    place, hole = f"{shared_folder(spark)}/spelt-{uuid.uuid4().hex}", np.iinfo(kind).max
    spelt = decoding_table(table) if check else None
    fields = [("n_tokens", T.LongType()), ("ids", T.ArrayType(T.IntegerType())), *([("round_trip", T.BooleanType())] if check else [])]
    schema = T.StructType([*(rows.schema["row"].dataType.fields if keep else []), *[T.StructField(f, t) for f, t in fields]])

    def finished(row, ids: np.ndarray, ends: np.ndarray, same):
        """A batch of results; ``same`` compares a row's decoded bytes with what is known of its text."""
        import pyarrow as pa

        columns = [pa.array(np.diff(ends), pa.int64()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(ids.astype(np.int32)))]
        if check:
            columns.append(pa.array([same(i, t) for i, t in enumerate(decode_rows(ids, ends, spelt))], pa.bool_()))
        return pa.RecordBatch.from_arrays([*(row.flatten() if keep else []), *columns], names=[*keep, *[f for f, _ in fields]])

    def in_portions(batches, lacking: dict):
        """row, texts, ids, ends of the rows' ids, numbers of the missing units and ends of the rows' numbers."""
        cutter, head = Cutter(table), Head(paths, kind)
        for b in batches:
            every = b.column(1).to_pylist()
            for x, y in portions(every):
                made, sizes, holes, missing = [np.zeros(0, kind)], np.zeros(y - x, np.int64), np.zeros(y - x, np.int64), [np.zeros(0, np.int32)]
                for block, heads, owner in cutter.blocks(every[x:y]):
                    h, k = hashes(block, heads)
                    ids, n, gone = head.spell(h, k, hole)
                    made.append(ids)
                    sizes += np.bincount(owner, n, y - x).astype(np.int64)
                    if len(gone):
                        holes += np.bincount(owner[gone], minlength=y - x)
                        missing.append(np.array([lacking.setdefault(p, len(lacking)) for p in zip(h[gone].tolist(), k[gone].tolist(), strict=True)], np.int32))
                yield b.column(0).slice(x, y - x), every[x:y], np.concatenate(made), np.r_[0, np.cumsum(sizes)], np.concatenate(missing), np.r_[0, np.cumsum(holes)]

    def whole(batches):
        for row, texts, ids, ends, _, _ in in_portions(batches, {}):
            yield finished(row, ids, ends, lambda i, t, texts=texts: t == (texts[i] or "").encode())

    if entries.filter(beyond).isEmpty():  # no hole anywhere
        return rows.mapInArrow(whole, schema)

    def spell(batches):
        """Writes a file with the rows, their ids with holes, the numbers of the units that belong there, and a digest of the text.
        Returns its name and the numbered units."""
        import pyarrow as pa
        from pyspark import TaskContext

        kinds = pa.schema([("part", pa.int32()), ("path", pa.string()), ("j", pa.int32()), ("h", pa.int64()), ("k", pa.int64())])
        part, lacking, out = TaskContext.get().partitionId(), {}, None
        store, top = open_store(place)
        path = f"{top}/{uuid.uuid4().hex}.arrows"
        for row, texts, ids, ends, missing, holes in in_portions(batches, lacking):
            lists = [pa.ListArray.from_arrays(pa.array(e, pa.int32()), pa.array(v)) for e, v in ((ends, ids), (holes, missing))]
            digests = pa.array([digest((t or "").encode()) if check else None for t in texts], pa.binary())
            batch = pa.RecordBatch.from_arrays([row, *lists, digests], names=["row", "ids", "holes", "digest"])
            if out is None:
                store.create_dir(top, recursive=True)
                sink = store.open_output_stream(path)
                out = pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd"))
            out.write_batch(batch)
        if out is not None:
            out.close()
            sink.close()
            yield pa.RecordBatch.from_pylist([{"part": part, "path": path}], schema=kinds)
            pairs = np.array(list(lacking), np.uint64).reshape(-1, 2)
            for i in range(0, len(pairs), 100_000):
                h, k = (np.ascontiguousarray(c).view(np.int64) for c in pairs[i : i + 100_000].T)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(h), part, np.int32)), pa.nulls(len(h), pa.string()), pa.array(np.arange(i, i + len(h), dtype=np.int32)), pa.array(h), pa.array(k)], schema=kinds)

    told = stash(rows.mapInArrow(spell, "part int, path string, j int, h long, k long"), "spelt")
    release(spark)
    files = told.filter("path IS NOT NULL").select("part", "path")
    spread = 3 * max(files.count(), 1)  # by number, so that the list of each file is made where it is used
    # A list per file: as many units as one task met.
    lacked = told.filter("path IS NULL").select("part", "j", "h", "k").join(entries.filter(beyond).select("h", "k", "code"), ["h", "k"])
    found = lacked.select("part", "j", "code").repartition(spread, "part").groupBy("part").agg(F.collect_list(F.struct("j", "code")).alias("more"))

    def fill(batches):
        import pyarrow as pa
        import pyarrow.compute as pc

        for b in batches:
            for path, more in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                more = more.values
                if more is not None:
                    code = more.field("code")
                    order = np.argsort(more.field("j").to_numpy())
                    sizes = pc.binary_length(code).to_numpy()[order] // kind.itemsize
                    flat = np.frombuffer(b"".join(code.take(pa.array(order)).to_pylist()), kind)
                    begins = np.cumsum(sizes) - sizes
                store, _ = open_store(place)
                with store.open_input_stream(path) as source:
                    for r in pa.ipc.open_stream(source):
                        ids, ends = r.column(1).flatten().to_numpy(), np.r_[0, np.cumsum(r.column(1).value_lengths().to_numpy())]
                        at = r.column(2).flatten().to_numpy()
                        if len(at):
                            n, from_, gone = np.ones(len(ids), np.int64), np.arange(len(ids)), np.flatnonzero(ids == hole)
                            n[gone], from_[gone] = sizes[at], len(ids) + begins[at]
                            ids, ends = np.concatenate([ids, flat])[stretches(from_, n)], np.r_[0, np.cumsum(n)][ends]
                        known = r.column(3).to_pylist()
                        yield finished(r.column(0), ids, ends, lambda i, t, known=known: digest(t) == known[i])

    return files.repartition(spread, "part").join(found, "part", "left").select("path", "more").mapInArrow(fill, schema)


def decoding_table(table: PieceTable) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes that ids stand for, one after the other, and by id the start and the number of its bytes."""
    out = [b""] * (max([table.unknown_id, table.bytes_from + 255, *(i for i, _ in table.pieces.values())]) + 1)
    for p, (i, _) in table.pieces.items():
        out[i] = p.replace(SPACE_MARK, " ").encode()
    if table.bytes_from >= 0:
        for v in range(256):
            out[table.bytes_from + v] = bytes([v])
    sizes = np.array(list(map(len, out)))
    return np.frombuffer(b"".join(out), np.uint8), np.cumsum(sizes) - sizes, sizes


def decode_bytes(ids: np.ndarray, spelt: tuple[np.ndarray, np.ndarray, np.ndarray], first: bool = True) -> bytes:
    """UTF-8 of the ids, if they are the first without the space that encoding put in front."""
    found, starts, sizes = spelt
    data = found[stretches(starts[ids], sizes[ids])].tobytes()
    return data[1:] if first and data.startswith(b" ") else data


def decode_rows(ids: np.ndarray, ends: np.ndarray, spelt: tuple[np.ndarray, np.ndarray, np.ndarray]):
    """The UTF-8 bytes of each row's ids; at once where they are few, else row by row and stretch by stretch."""
    if len(ids) <= 1 << 21:
        found, starts, sizes = spelt
        size = sizes[ids]
        data, at = found[stretches(starts[ids], size)].tobytes(), np.r_[0, np.cumsum(size)][ends].tolist()
        for a, b in zip(at[:-1], at[1:], strict=True):
            yield data[a + 1 : b] if data[a : a + 1] == b" " and b > a else data[a:b]
        return
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
        yield b"".join([decode_bytes(ids[i : min(b, i + (1 << 20))], spelt, i == a) for i in range(a, b, 1 << 20)])


def decode_ids(ids: np.ndarray, spelt: tuple[np.ndarray, np.ndarray, np.ndarray]) -> str:
    """The text of the ids."""
    return decode_bytes(ids, spelt).decode("utf-8", "replace")


def decode(encoded: DataFrame, table: PieceTable, keep: list[str]) -> DataFrame:
    """``keep`` columns and ``text`` of rows with ``ids``."""
    spelt = decoding_table(table)

    @F.arrow_udf(T.StringType())
    def text(ids):
        import pyarrow as pa

        return pa.array([decode_ids(np.array(x or [], np.int64), spelt) for x in ids.to_pylist()], pa.string())

    return encoded.select(*[F.col(f"`{c}`") for c in keep], text(F.col("ids")).alias("text"))
