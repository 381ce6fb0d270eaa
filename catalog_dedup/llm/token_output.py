"""Token ids in binary shards: byte planes, compressed one by one, with a chunk index.

Documents are range-partitioned and sorted by doc_id (nulls first, then by text); each partition tokenizes its whole texts,
ends each with ``END`` and writes one shard to the shared folder. Ids go into blocks of ``BLOCK``; a block's ids, 32 bits
each, are transposed into four byte planes, and each plane is compressed with zstandard. Spaces between words are tokenizer
boundaries, so ids of words are remembered and joined; what a tokenizer would do with a whole text is unchanged.

Shard layout, all numbers little-endian: 8 bytes MAGIC; the compressed planes; a compressed table of documents (a byte
that tells null ids, then an int64 id and a uint32 count for each); the chunk index (for each block its offset as uint64,
its number of ids and the four lengths as uint32); a footer of five uint64 (offsets of table and index, blocks, documents,
ids) and MAGIC again.

A task writes under a name of its own and the manifest names only shards of tasks that ended well, so a lost executor or a
second attempt leaves nothing wrong. Null and empty texts have the end id alone. Rows may repeat. An empty table gives none.
"""

from __future__ import annotations

import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import open_store, shared_folder, stash

BLOCK = 65536
MAGIC = b"BPLANES1"
END = 1
#: Bytes of text that a task tokenizes, about: words are remembered within a task, so that larger ones learn fewer words again.
SHARD_BYTES = 128 << 20
#: Words that a task remembers before it starts anew (about 250 MB).
REMEMBERED = 1_000_000
_FOOTER = "<5Q8s"


def byte_letters() -> list[str]:
    """The letter that byte-level vocabularies write for each byte: printable Latin-1 stands for itself, others count up from 256."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = iter(range(256, 512))
    return [chr(b if b in own else next(rest)) for b in range(256)]


def word_tokenizer(path: str):
    """texts (str or UTF-8 bytes) -> list of bytes (uint32 ids). Splits at ASCII white space, which this vocabulary's own splitter
    never crosses, as ``bytes.split`` does.

    Words are remembered. Those of Latin letters alone, perhaps with full stops or commas behind, are one pre-token (and one
    of marks), so their lower-cased bytes go straight to the vocabulary's merges; others take the tokenizer's whole way.
    """
    import re
    from array import array

    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(path)
    merges = tok.model.tokenize
    letters = byte_letters()
    # Latin letters that have one small letter each and that normalisation leaves alone (not the dotted capital I).
    simple = re.compile("([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u024f]+)([.,]*)").fullmatch
    heads: dict[str, bytes] = {}

    def whole(text: str) -> bytes:
        return array("I", tok.encode(text, add_special_tokens=False).ids).tobytes()

    def learn(word: str) -> bytes:
        found = simple(word)
        if not found:
            return whole(word)
        head, marks = found.groups()
        head = head.lower()
        ids = heads.get(head)
        if ids is None:
            spelt = head if head.isascii() else "".join([letters[b] for b in head.encode()])
            ids = heads[head] = array("I", [x.id for x in merges(spelt)]).tobytes()
        if marks:
            if marks not in heads:
                heads[marks] = whole(marks)
            ids += heads[marks]
        return ids

    class Memo(dict):
        def __missing__(self, word: bytes) -> bytes:
            ids = self[word] = learn(word.decode())
            return ids

    memo = Memo()

    def encode(texts: list[str | bytes | None]) -> list[bytes]:
        out = []
        for t in texts:
            if len(memo) > REMEMBERED:
                memo.clear()
                heads.clear()
            words = (t.encode() if isinstance(t, str) else t).split() if t else []
            out.append(b"".join(map(memo.__getitem__, words)))
        return out

    return encode


class ShardWriter:
    """Appends documents to one shard; holds a block of ids and the table of documents."""

    def __init__(self, sink):
        import zstandard

        self.sink, self.zip = sink, zstandard.ZstdCompressor(level=3)
        self.at, self.waiting, self.held, self.ids = len(MAGIC), [], 0, 0
        self.index, self.keys, self.nulls, self.counts = bytearray(), [], bytearray(), []
        sink.write(MAGIC)

    def add(self, doc_id: int | None, ids: bytes) -> None:
        self.nulls.append(doc_id is None)
        self.keys.append(doc_id or 0)
        self.counts.append(len(ids) // 4)
        self.waiting.append(ids)
        self.held += len(ids)
        while self.held >= 4 * BLOCK:
            data = b"".join(self.waiting)
            self._block(data[: 4 * BLOCK])
            self.waiting, self.held = [data[4 * BLOCK :]], len(data) - 4 * BLOCK

    def _put(self, data: bytes) -> int:
        self.sink.write(data)
        self.at += len(data)
        return len(data)

    def _block(self, data: bytes) -> None:
        planes = np.frombuffer(data, np.uint8).reshape(-1, 4).T
        start = self.at
        lengths = [self._put(self.zip.compress(np.ascontiguousarray(p).tobytes())) for p in planes]
        self.index += struct.pack("<Q5I", start, len(data) // 4, *lengths)
        self.ids += len(data) // 4

    def close(self) -> None:
        if self.held:
            self._block(b"".join(self.waiting))
        table = self.at
        self._put(self.zip.compress(bytes(self.nulls) + np.array(self.keys, "<i8").tobytes() + np.array(self.counts, "<u4").tobytes()))
        index = self.at
        self._put(bytes(self.index))
        self.sink.write(struct.pack(_FOOTER, table, index, len(self.index) // 28, len(self.keys), self.ids, MAGIC))


def read_shard(source) -> Iterator[tuple[int | None, bytes]]:
    """(doc_id, ids as uint32 bytes) of each document in order; holds one block beyond the document at hand."""
    import zstandard

    unzip = zstandard.ZstdDecompressor()
    source.seek(source.size() - struct.calcsize(_FOOTER))
    table, index, blocks, docs, ids, magic = struct.unpack(_FOOTER, source.read(struct.calcsize(_FOOTER)))
    if magic != MAGIC:
        raise ValueError("not a shard of byte planes")
    source.seek(table)
    data = unzip.decompress(source.read(index - table))
    nulls, keys, counts = data[:docs], np.frombuffer(data, "<i8", docs, docs), np.frombuffer(data, "<u4", docs, 9 * docs)
    chunks = list(struct.iter_unpack("<Q5I", source.read(28 * blocks)))
    held, k = b"", 0
    for i in range(docs):
        need, parts, have = 4 * int(counts[i]), [held], len(held)
        while have < need:
            start, n, *lengths = chunks[k]
            source.seek(start)
            planes = [np.frombuffer(unzip.decompress(source.read(x)), np.uint8) for x in lengths]
            parts.append(np.stack(planes, 1).tobytes())
            have, k = have + 4 * n, k + 1
        data = b"".join(parts) if len(parts) > 1 else held
        yield (None if nulls[i] else int(keys[i])), data[:need]
        held = data[need:]


def write_shards(docs: DataFrame, vocabulary: str, end: int = END, folder: str | None = None) -> DataFrame:
    """Write the ids of all rows; returns the manifest: shard (number), path, docs, ids and start (ids in earlier shards)."""
    folder = folder or f"{shared_folder(docs.sparkSession)}/token-shards-{uuid.uuid4().hex}"
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    rows = docs.select("doc_id", "text").repartitionByRange(max(1, -(-size // SHARD_BYTES)), F.col("doc_id").asc_nulls_first(), F.xxhash64("text")).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))
    rows = rows.select("doc_id", F.col("text").cast("binary").alias("text"))  # words are looked up by their bytes
    last = np.array([end], np.uint32).tobytes()

    def write(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        store, top = open_store(folder)
        store.create_dir(top, recursive=True)
        number, path = TaskContext.get().partitionId(), f"{top}/shard-{uuid.uuid4().hex}.bpl"
        encode, writer = None, None
        for b in batches:
            for i in range(0, b.num_rows, 512):
                part = b.slice(i, 512)
                if writer is None:
                    sink = store.open_output_stream(path)
                    encode, writer = word_tokenizer(vocabulary), ShardWriter(sink)
                for key, ids in zip(part.column(0).to_pylist(), encode(part.column(1).to_pylist()), strict=True):
                    writer.add(key, ids + last)
        if writer:
            writer.close()
            sink.close()
            yield pa.RecordBatch.from_pylist([{"shard": number, "path": path, "docs": len(writer.keys), "ids": writer.ids}], schema=pa.schema([("shard", pa.int32()), ("path", pa.string()), ("docs", pa.int64()), ("ids", pa.int64())]))

    manifest = stash(rows.mapInArrow(write, "shard int, path string, docs long, ids long"), "manifest")
    before = F.sum("ids").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))  # one row a shard
    return stash(manifest.withColumn("start", F.coalesce(before, F.lit(0))).withColumn("store", F.lit(folder)), "manifest")


def read_shards(manifest: DataFrame, digest: bool = False) -> DataFrame:
    """doc_id, start, n_tokens and ids (binary, uint32) of every document, from the shards; ``digest``: ids_crc32 in place of ids."""
    last = "ids_crc32 long" if digest else "ids binary"

    def read(batches):
        import pyarrow as pa

        kinds = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64()) if digest else ("ids", pa.binary())])
        for b in batches:
            for r in b.to_pylist():
                store, _ = open_store(r["store"])
                with store.open_input_file(r["path"]) as source:
                    at, out, size = r["start"], [], 0
                    for key, ids in read_shard(source):
                        out.append((key, at, len(ids) // 4, zlib.crc32(ids) if digest else ids))
                        at += len(ids) // 4
                        size += len(ids)
                        if size > 8 << 20 or len(out) >= 10_000:
                            yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], schema=kinds)
                            out, size = [], 0
                    if out:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], schema=kinds)

    shards = max(manifest.count(), 1)
    return manifest.repartition(shards).mapInArrow(read, f"doc_id long, start long, n_tokens long, {last}")
