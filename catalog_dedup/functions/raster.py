"""Gray images: rendered listings, patches, cropping. Integer arithmetic where results are compared."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SIDE, PATCH = 24, 8
#: Gray range that vectors are mapped from: x to floor((x + LOW) / RANGE * 255), clipped.
LOW, RANGE = 0.6, 1.2
#: What a picture is put together from, and how many there are of each: at most 3,687,936 pictures, however many listings.
PARTS = {"kind": 6, "texture": 7, "gray": 8, "brand": 32, "half": 49, "noise": 7}


def cells(images: np.ndarray) -> np.ndarray:
    """(n, 24, 24) -> (n, 9, 64)."""
    return images.reshape(len(images), 3, PATCH, 3, PATCH).swapaxes(2, 3).reshape(len(images), 9, PATCH * PATCH)


def uncells(x: np.ndarray) -> np.ndarray:
    return x.reshape(len(x), 3, 3, PATCH, PATCH).swapaxes(2, 3).reshape(len(x), SIDE, SIDE)


def shrunk(images: np.ndarray) -> np.ndarray:
    """The whole image as one patch: means of 3 x 3 pixels."""
    return images.reshape(len(images), PATCH, 3, PATCH, 3).mean((2, 4)).reshape(len(images), -1)


def _mix(keys: np.ndarray, seed: int) -> np.ndarray:
    x = (keys + np.uint64(seed)) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(31))


def random_cells(keys: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """k distinct cells of the nine, by a hash of the key."""
    scores = np.stack([_mix(keys ^ np.uint64(7919 * (c + 1)), seed) for c in range(9)], 1)
    return np.argsort(scores, 1)[:, :k]


def guided_cells(keys: np.ndarray, seed: int = 0) -> np.ndarray:
    """Centre, two distinct others, and 9 for the shrunk whole."""
    h = _mix(keys, seed) >> np.uint64(11)
    i, j = (h % np.uint64(8)).astype(int), ((h // np.uint64(8)) % np.uint64(7)).astype(int)
    j += j >= i
    cell = lambda x: np.where(x < 4, x, x + 1)  # the centre, 4, is not among the eight
    return np.stack([np.full(len(keys), 4), cell(i), cell(j), np.full(len(keys), 9)], 1)


def crop_to_object(image: np.ndarray, background: int = 255) -> np.ndarray:
    """Cut to the box of pixels that differ from the background and resized to the input's side (nearest); blank images stay."""
    differs = image != background
    if not differs.any():
        return image
    rows, cols = np.flatnonzero(differs.any(1)), np.flatnonzero(differs.any(0))
    part = image[rows[0] : rows[-1] + 1, cols[0] : cols[-1] + 1]
    h, w = image.shape
    return part[np.arange(h) * part.shape[0] // h][:, np.arange(w) * part.shape[1] // w]


def unpack(pixels: list[bytes]) -> np.ndarray:
    """(n, 24, 24) in 0..1."""
    return np.frombuffer(b"".join(pixels), np.uint8).reshape(-1, SIDE, SIDE) / 255.0


def draw(kind: int, texture: int, gray: int, brand: int, size: int, h: int, seller: int) -> np.ndarray:
    """A 48 x 48 picture: silhouette, texture and gray of the product, a brand glyph in the centre, the seller's border and noise."""
    side = 48
    y, x = np.mgrid[:side, :side]
    border = 4 + h % 8 if seller % 2 else 0
    half = max(6, (16 + size * 24 // 50) * (side - 2 * border) // side // 2)
    dy, dx = y - 24, x - 24
    inside = [
        (abs(dx) <= half) & (abs(dy) <= half), dx * dx + dy * dy <= half * half, (dy >= -half) & (dy <= half) & (2 * abs(dx) <= dy + half),
        (dx * dx + dy * dy <= half * half) & (4 * (dx * dx + dy * dy) >= half * half), ((abs(dx) * 3 <= half) | (abs(dy) * 3 <= half)) & (abs(dx) <= half) & (abs(dy) <= half), (abs(dy) * 2 <= half) & (abs(dx) <= half),
    ][kind % 6]
    out = np.full((side, side), 255, np.int64)
    out[inside] = 60 + 16 * gray
    out[inside & ((x + y) // (2 + texture) % 2 == 0)] -= 30
    for bit in range(5):
        out[20 : 28, 19 + 2 * bit : 21 + 2 * bit] = 0 if brand >> bit & 1 else 200
    noise = (x * 31 + y * 17 + h) % 7 - 3
    out[inside] += noise[inside]
    return np.clip(out, 0, 255).astype(np.uint8)


def halve(image: np.ndarray) -> np.ndarray:
    return (image.reshape(SIDE, 2, SIDE, 2).astype(int).sum((1, 3)) // 4).astype(np.uint8)


def _shapes() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What pictures are put together from: silhouettes by kind and half size, stripes by texture, noise by h modulo 7."""
    y, x = np.mgrid[:48, :48]
    dy, dx = y - 24, x - 24
    inside = lambda half: [
        (abs(dx) <= half) & (abs(dy) <= half), dx * dx + dy * dy <= half * half, (dy >= -half) & (dy <= half) & (2 * abs(dx) <= dy + half),
        (dx * dx + dy * dy <= half * half) & (4 * (dx * dx + dy * dy) >= half * half), ((abs(dx) * 3 <= half) | (abs(dy) * 3 <= half)) & (abs(dx) <= half) & (abs(dy) <= half), (abs(dy) * 2 <= half) & (abs(dx) <= half),
    ]
    silhouettes = np.swapaxes(np.array([inside(half) for half in range(49)]), 0, 1)
    return silhouettes, np.array([(x + y) // (2 + t) % 2 == 0 for t in range(7)]), np.array([(x * 31 + y * 17 + h) % 7 - 3 for h in range(7)], np.int16)


def draw_all(kind: np.ndarray, texture: np.ndarray, gray: np.ndarray, brand: np.ndarray, size: np.ndarray, h: np.ndarray, seller: np.ndarray, shapes: tuple) -> np.ndarray:
    """``draw`` of many pictures (n, 48, 48). Half sizes are 48 at most."""
    border = np.where(seller % 2 != 0, 4 + h % 8, 0)
    half = np.maximum(6, (16 + size * 24 // 50) * (48 - 2 * border) // 48 // 2)
    return put_together(kind % 6, texture, gray, brand, np.minimum(half, 48), h % 7, shapes)


def put_together(kind: np.ndarray, texture: np.ndarray, gray: np.ndarray, brand: np.ndarray, half: np.ndarray, noise: np.ndarray, shapes: tuple) -> np.ndarray:
    silhouettes, stripes, noises = shapes
    inside = silhouettes[kind, half]
    ink = (60 + 16 * gray).astype(np.int16)[:, None, None]
    out = np.where(inside, ink - 30 * stripes[texture].astype(np.int16), np.int16(255))
    bits = np.where(brand[:, None] >> np.arange(5) & 1, 0, 200).astype(np.int16)
    out[:, 20:28, 19:29] = np.repeat(bits, 2, 1)[:, None]
    out += noises[noise] * inside
    return np.clip(out, 0, 255).astype(np.uint8)


def draw_codes(codes: np.ndarray, shapes: tuple) -> np.ndarray:
    """Pictures (n, 48, 48) of codes that ``coded`` gives."""
    return put_together(*np.unravel_index(codes, tuple(PARTS.values())), shapes)


def crop_all(images: np.ndarray, background: int = 255) -> np.ndarray:
    """``crop_to_object`` of each picture."""
    differs = images != background
    n, height, width = images.shape

    def places(any_of: np.ndarray, side: int) -> np.ndarray:
        blank = ~any_of.any(1)
        first, last = any_of.argmax(1), side - 1 - any_of[:, ::-1].argmax(1)
        first, last = np.where(blank, 0, first), np.where(blank, side - 1, last)
        return first[:, None] + np.arange(side) * (last - first + 1)[:, None] // side

    return images[np.arange(n)[:, None, None], places(differs.any(2), height)[:, :, None], places(differs.any(1), width)[:, None, :]]


def halve_all(images: np.ndarray) -> np.ndarray:
    wide = images.astype(np.uint16)
    return ((wide[:, ::2, ::2] + wide[:, ::2, 1::2] + wide[:, 1::2, ::2] + wide[:, 1::2, 1::2]) // 4).astype(np.uint8)


def coded(listings: DataFrame) -> DataFrame:
    """id and code of listings: the parts of a listing's picture as one number, so that equal codes are equal pictures. Unknown parts count as 0."""
    border = F.when(F.pmod("seller", F.lit(2)) != 0, F.pmod("h", F.lit(8)) + 4).otherwise(0)
    parts = {
        "kind": F.pmod(F.xxhash64("p_type"), F.lit(6)), "texture": F.pmod(F.crc32(F.element_at(F.split("p_name", " "), 2)), F.lit(7)), "gray": F.pmod(F.crc32(F.element_at(F.split("p_name", " "), 1)), F.lit(8)),
        "brand": F.pmod(F.regexp_extract("p_brand", r"(\d+)", 1).cast("int"), F.lit(32)), "half": F.least(F.lit(48), F.greatest(F.lit(6), F.floor((F.floor(F.col("p_size").cast("long") * 24 / 50) + 16) * (48 - border * 2) / 96))), "noise": F.pmod("h", F.lit(7)),
    }
    code = F.lit(0).cast("long")
    for name, n in PARTS.items():
        code = code * n + F.coalesce(parts[name].cast("long"), F.lit(0).cast("long"))
    return listings.select(F.col("listing_id").alias("id"), code.cast("int").alias("code"))


def keyed(rows: DataFrame) -> DataFrame:
    """id, key, code of coded listings; the key draws what is random about a listing's picture."""
    return rows.select("id", F.abs(F.xxhash64("id")).alias("key"), "code")


def rendered(listings: DataFrame, crop: float = 0.0, other: float | None = None) -> DataFrame:
    """``pictures`` of listings."""
    return pictures(coded(listings), crop, other)


def pictures(rows: DataFrame, crop: float = 0.0, other: float | None = None) -> DataFrame:
    """id, key, pixels (24 x 24) of coded listings, and with ``other`` the same pictures at that crop as ``other``. ``crop`` is the share of pictures whose seller's border is cut away first: 0 none, 1 all,
    anything between by a hash-random draw for each picture, the augmentation of a training loader."""
    crops = [crop] if other is None else [crop, other]

    def run(batches):
        import pyarrow as pa

        shapes = _shapes()
        for b in batches:
            for i in range(0, b.num_rows, 512):
                part = b.slice(i, 512)
                key, code = (part.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in (1, 2))
                whole, made = draw_codes(code, shapes), []
                for share in crops:
                    cut, images = key % 9973 < 9973 * share, whole.copy()
                    images[cut] = crop_all(whole[cut])
                    data = halve_all(images)
                    made.append(pa.Array.from_buffers(pa.binary(), len(key), [None, pa.py_buffer(np.arange(0, data.size + 1, SIDE * SIDE, dtype=np.int32)), pa.py_buffer(np.ascontiguousarray(data))]))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *made], names=["id", "key", "pixels", "other"][: 2 + len(made)])

    return keyed(rows).mapInArrow(run, "id long, key long, pixels binary" + ", other binary" * (len(crops) - 1))


def vector_pixels(df: DataFrame) -> DataFrame:
    """vec_id, row, col, gray: the 64 components as an 8 x 8 picture, enlarged to 9 x 9 by nearest neighbours."""
    gray = F.transform("embedding", lambda x: F.greatest(F.lit(0), F.least(F.lit(255), F.floor((x.cast("double") + LOW) / RANGE * 255).cast("int"))))
    big = F.transform(F.sequence(F.lit(0), F.lit(80)), lambda i: F.get("g", (F.floor(i / 9) * 8 / 9).cast("int") * 8 + (i % 9 * 8 / 9).cast("int")))
    return df.select("vec_id", gray.alias("g")).select("vec_id", F.posexplode(big).alias("i", "gray")).select("vec_id", F.floor(F.col("i") / 9).cast("long").alias("row"), (F.col("i") % 9).cast("long").alias("col"), F.col("gray").cast("long").alias("gray"))
