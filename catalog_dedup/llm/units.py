"""Whole texts cut into the units of a piece table and hashed, a block of characters at a time.

A unit is a longest run of characters in which every two neighbours stand side by side in some piece: no piece crosses a cut, so
a text's best segmentation is that of its units, one after the other. A space counts as the space mark, and a text gets one in
front. As no piece holds a mark behind another character, every run of spaces begins a unit.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from .pieces import SPACE_MARK, PieceTable

#: Characters that are worked on at a time; a longer unit is worked on as a whole.
SLICE = 1 << 19
_MARK = ord(SPACE_MARK)

#: codes of a block's characters, heads of its units (and the end), and the number of each unit's text.
Block = tuple[np.ndarray, np.ndarray, np.ndarray]


def codes_of(text: str) -> np.ndarray:
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).copy()
    codes[codes == 32] = _MARK
    return codes


def hashes(codes: np.ndarray, heads: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each unit 64 and 32 bits that tell it from all others: sums over its characters of a mixed number of character and place."""
    x = (np.arange(len(codes)) - np.repeat(heads[:-1], np.diff(heads))).astype(np.uint64)
    x *= np.uint64(0x110000)
    x += codes
    x += np.uint64(0x9E3779B97F4A7C15)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x ^= x >> np.uint64(shift)
        x *= np.uint64(factor)
    x ^= x >> np.uint64(31)
    first = np.add.reduceat(x, heads[:-1]) if len(heads) > 1 else np.zeros(0, np.uint64)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    second = np.add.reduceat(x, heads[:-1]) if len(heads) > 1 else np.zeros(0, np.uint64)
    return first, (second >> np.uint64(32)).astype(np.uint32)


def hashes_of(units: list[str]) -> tuple[np.ndarray, np.ndarray]:
    return hashes(codes_of("".join(units)), np.r_[0, np.cumsum(np.fromiter(map(len, units), np.int64, len(units)))].astype(np.int64))


class Cutter:
    """Cuts texts where two neighbouring characters stand side by side in no piece."""

    def __init__(self, table: PieceTable):
        places = {c: i + 1 for i, c in enumerate(sorted({c for p in table.pieces if len(p) > 1 for c in p}))}
        self.wide = len(places) + 1
        self.place = np.zeros(0x110000, np.int32)
        self.place[[ord(c) for c in places]] = list(places.values())
        self.inside = np.zeros(self.wide * self.wide, bool)
        self.inside[[places[p[i]] * self.wide + places[p[i + 1]] for p in table.pieces for i in range(len(p) - 1)]] = True

    def heads(self, codes: np.ndarray, texts: list[int]) -> np.ndarray:
        """Where units begin; ``texts``: where texts begin."""
        at = self.place[codes]
        begins = np.ones(len(codes), bool)
        begins[1:] = ~self.inside[at[:-1] * self.wide + at[1:]]
        begins[texts] = True
        return np.flatnonzero(begins)

    def blocks(self, texts: list[str | None]) -> Iterator[Block]:
        """Blocks of whole units in order. Null and empty texts have none."""
        parts, owners, size = [], [], 0
        for k, t in enumerate(texts):
            if not t:
                continue
            if size and size + len(t) >= SLICE:
                yield self._block(parts, owners)
                parts, owners, size = [], [], 0
            if len(t) >= SLICE:
                yield from self._long(k, t)
            else:
                parts.append(SPACE_MARK + t)
                owners.append(k)
                size += len(t) + 1
        if parts:
            yield self._block(parts, owners)

    def _block(self, parts: list[str], owners: list[int]) -> Block:
        ends = np.cumsum(list(map(len, parts)))
        codes = codes_of("".join(parts))
        heads = self.heads(codes, [0, *ends[:-1].tolist()])
        owner = np.repeat(np.array(owners), np.diff(np.r_[0, np.searchsorted(heads, ends)]))
        return codes, np.r_[heads, len(codes)], owner

    def _long(self, k: int, text: str) -> Iterator[Block]:
        text, at, size = SPACE_MARK + text, 0, SLICE
        while at < len(text):
            codes = codes_of(text[at : at + size])
            heads = self.heads(codes, [0])
            if at + size < len(text):  # the last unit may go on
                if len(heads) == 1:
                    size *= 2
                    continue
                codes, heads = codes[: heads[-1]], heads[:-1]
            yield codes, np.r_[heads, len(codes)], np.full(len(heads), k)
            at, size = at + len(codes), SLICE


def portions(texts: list[str | None]) -> Iterator[tuple[int, int]]:
    """Ranges of rows with about SLICE characters each, or of one longer text."""
    start = size = 0
    for k, t in enumerate(texts):
        n = len(t or "")
        if k > start and (size + n > SLICE or k - start >= 4096):
            yield start, k
            start, size = k, 0
        size += n
    if len(texts) > start:
        yield start, len(texts)
