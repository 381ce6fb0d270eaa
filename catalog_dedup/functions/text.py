"""Title handling with built-in expressions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}]+"
FIRST = 32
WIDTH = 128


def normalise(text: Column) -> Column:
    """Lower case, everything but letters and digits as single spaces, trimmed."""
    return F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(TOKEN), F.lit(0))


def first_tokens(text: Column, limit: int = FIRST) -> Column:
    """The first ``limit`` tokens; what lies beyond never leaves this expression."""
    return F.slice(tokens(text), 1, limit)


def token_hash(token: Column) -> Column:
    """32 hash bits that every engine with md5 agrees on."""
    return F.conv(F.substring(F.md5(token), 1, 8), 16, 10).cast("long")


def hashed_features(df: DataFrame, key: str, text: str, limit: int = FIRST, width: int = WIDTH) -> DataFrame:
    """Signed hashed token counts in long form: key, dim, val (val not 0)."""
    each = df.select(key, F.explode(first_tokens(F.col(text), limit)).alias("tok")).withColumn("h", token_hash(F.col("tok")))
    signed = each.select(key, (F.col("h") % width).alias("dim"), F.when(F.shiftright("h", 16) % 2 == 1, -1).otherwise(1).alias("v"))
    return signed.groupBy(key, "dim").agg(F.sum("v").alias("val")).filter("val != 0")


def token_counter(width: int):
    """A function from an Arrow list of token lists to the matrix of their signed hashed counts, zeros for null. A token is hashed once a
    task as long as its hash is remembered."""
    from hashlib import md5

    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    known: dict[bytes, int] = {}

    def hashed(token: bytes) -> int:
        if token not in known:
            if len(known) > 1_000_000:
                known.clear()
            known[token] = int(md5(token).hexdigest()[:8], 16)
        return known[token]

    def count(tokens) -> np.ndarray:
        tokens = tokens.combine_chunks() if isinstance(tokens, pa.ChunkedArray) else tokens
        sizes = pc.fill_null(pc.list_value_length(tokens), 0).to_numpy(zero_copy_only=False)
        each = tokens.flatten().dictionary_encode()
        h = np.array([hashed(t) for t in each.dictionary.cast(pa.binary()).to_pylist()], np.int64)[each.indices.to_numpy()]
        at = np.repeat(np.arange(len(sizes)), sizes) * width + h % width
        return np.bincount(at, 1 - 2 * (h >> 16 & 1), len(sizes) * width).reshape(-1, width)

    return count


def dense_features(df: DataFrame, key: str, text: str, limit: int = FIRST, width: int = WIDTH) -> DataFrame:
    """The same as one array<int> a row, without a shuffle: tokens are found in the JVM, hashed and counted a batch at a time. A text that
    is null or has no token gives zeros."""

    @F.arrow_udf("array<int>")
    def counted(tokens):
        import numpy as np
        import pyarrow as pa

        out = token_counter(width)(tokens).ravel().astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(np.arange(0, len(out) + 1, width), pa.int32()), pa.array(out))

    return df.withColumn("vec", counted(first_tokens(F.col(text), limit)))


def packed_features(df: DataFrame, key: str, text: str, width: int = WIDTH) -> DataFrame:
    """id, vec: ``dense_features`` as ``width`` signed bytes a row (the first 32 tokens count to 32 at most). Rows of zeros are left out."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        count = token_counter(width)
        for b in batches:
            for i in range(0, b.num_rows, 4096):  # bounds the counts in double precision
                part = b.slice(i, 4096)
                x = count(part.column(1)).astype(np.int8)
                some = x.any(1)
                yield pa.RecordBatch.from_arrays([part.column(0).filter(pa.array(some)), packed(x[some])], names=["id", "vec"])

    return df.select(F.col(key).cast("long"), first_tokens(F.col(text))).mapInArrow(run, "id long, vec binary")


def packed(x):
    """The rows of a matrix of signed bytes as an Arrow array of binary."""
    import numpy as np
    import pyarrow as pa

    ends = np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)
    return pa.Array.from_buffers(pa.binary(), len(x), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(x))])


GENERIC_WIDTH, GRAM = 512, 3


def grams(text: Column) -> Column:
    """Character 3-grams of the normalised text."""
    t = normalise(text)
    return F.when(F.length(t) >= GRAM, F.transform(F.sequence(F.lit(1), F.length(t) - (GRAM - 1)), lambda i: F.substring(t, i, F.lit(GRAM)))).otherwise(F.array().cast("array<string>"))


def generic_features(df: DataFrame, key: str, text: str, width: int = GENERIC_WIDTH) -> DataFrame:
    """Stand-in for a general sentence encoder that has never seen the catalogue: hashed character 3-grams of the whole text in long
    form: key, dim, val."""
    each = df.select(key, F.explode(grams(F.col(text))).alias("g")).withColumn("h", token_hash(F.col("g")))
    signed = each.select(key, (F.col("h") % width).alias("dim"), F.when(F.shiftright("h", 16) % 2 == 1, -1).otherwise(1).alias("v"))
    return signed.groupBy(key, "dim").agg(F.sum("v").alias("val")).filter("val != 0")


def generic_digest(df: DataFrame, key: str, text: str, width: int = GENERIC_WIDTH) -> DataFrame:
    """key, n_dims, n2, moment of each row's ``generic_features`` (numbers that are not 0, their squares' sum, and the sum of dim * val),
    a batch at a time and without a shuffle; rows without such a number are left out. A 3-gram is hashed once a task."""
    rows = df.select(F.col(key), normalise(F.col(text)).alias("text"))

    def digest(batches):
        from hashlib import md5

        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        known: dict[int, int] = {}

        def hashed(gram: int) -> int:
            if gram not in known:
                if len(known) > 1_000_000:
                    known.clear()
                letters = "".join(chr(gram >> k & 0x1FFFFF) for k in (42, 21, 0))
                known[gram] = int(md5(letters.encode()).hexdigest()[:8], 16)
            return known[gram]

        for b in batches:
            for i in range(0, b.num_rows, 1024):
                part = b.slice(i, 1024)
                texts = pc.fill_null(part.column(1), "")
                codes = np.frombuffer("".join(texts.to_pylist()).encode("utf-32-le"), "<u4").astype(np.int64)
                row = np.repeat(np.arange(part.num_rows), pc.utf8_length(texts).to_numpy())
                inside = row[2:] == row[:-2]
                grams, at = np.unique((codes[:-2] << 42 | codes[1:-1] << 21 | codes[2:])[inside], return_inverse=True)
                h = np.array([hashed(g) for g in grams.tolist()], np.int64)[at]
                m = np.bincount(row[2:][inside] * width + h % width, 1 - 2 * (h >> 16 & 1), part.num_rows * width).astype(np.int64).reshape(-1, width)
                made = [(m != 0).sum(1), (m * m).sum(1), (m * np.arange(width)).sum(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), *map(pa.array, made)], names=[key, "n_dims", "n2", "moment"]).filter(pa.array(made[0] > 0))

    kind = rows.schema[key].dataType.simpleString()
    return rows.mapInArrow(digest, f"`{key}` {kind}, n_dims long, n2 long, moment long")


def budget_coverage(df: DataFrame, text: str, limits: tuple[int, ...] = (8, 16, 32, 64)) -> DataFrame:
    """Share of rows whose tokens all fit each budget."""
    n = df.select(F.size(tokens(F.col(text))).alias("n"))
    each = F.explode(F.array(*map(F.lit, limits))).alias("budget")
    return n.select("n", each).groupBy("budget").agg(F.count("*").alias("n_rows"), F.sum((F.col("n") <= F.col("budget")).cast("long")).alias("n_covered"))


def fit_vocabulary(df: DataFrame, text: str, size: int) -> DataFrame:
    """The ``size`` most frequent tokens with their counts; ties by token."""
    counts = df.select(F.explode(tokens(F.col(text))).alias("token")).groupBy("token").agg(F.count("*").alias("n"))
    return counts.orderBy(F.desc("n"), "token").limit(size)
