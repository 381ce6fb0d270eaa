"""The piece table of a SentencePiece file, read as a unigram lexicon, and the pre-tokens its segmentations can't cross."""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np

#: The mark that stands for a space.
SPACE_MARK = "▁"


@dataclass(frozen=True)
class PieceTable:
    """pieces: text -> (id, score) of the usable pieces; unknown: score of a character that is no piece; bytes_from: id of the
    first of the 256 byte pieces that spell such a character, or -1; unknown_id: what it gets if there are none."""

    pieces: dict[str, tuple[int, float]]
    longest: int
    unknown: float
    bytes_from: int
    unknown_id: int


def load(path: str) -> PieceTable:
    """Pieces of the file with their scores, those of several space marks alone among them."""
    from sentencepiece import SentencePieceProcessor

    m = SentencePieceProcessor(model_file=path)
    pieces, bytes_from = {}, -1
    for i in range(m.vocab_size()):
        p = m.id_to_piece(i)
        if m.is_byte(i):
            bytes_from = i if p == "<0x00>" else bytes_from
        elif not (m.is_control(i) or m.is_unknown(i) or m.is_unused(i)):
            pieces[p] = (i, m.get_score(i))
    if any(SPACE_MARK in p.lstrip(SPACE_MARK) for p in pieces):
        raise ValueError("a piece holds a space mark after another character")
    return PieceTable(pieces, max(map(len, pieces)), min(s for _, s in pieces.values()) - 10, bytes_from, m.unk_id())


def pre_token_pattern(table: PieceTable) -> str:
    """Pre-tokens: a run of space marks with what follows; a line break alone if no piece holds one."""
    stop = SPACE_MARK + ("" if any("\n" in p for p in table.pieces) else "\n")
    return f"{SPACE_MARK}+[^{stop}]*|[^{stop}]+|\n"


def splitter(table: PieceTable):
    """text -> list of pre-tokens; the text gets a space in front, as SentencePiece adds one. Null and empty texts have none."""
    find = re.compile(pre_token_pattern(table)).findall
    return lambda text: find(SPACE_MARK + text.replace(" ", SPACE_MARK)) if text else []


def chunker(table: PieceTable):
    """text -> list of chunks between spaces, much as pre-tokens but faster to get: the first mark in front is left out (others
    of its run stay, as spaces), and a line break that no piece holds begins a chunk which has no mark. Null and empty texts
    have none."""
    bare = not any("\n" in p for p in table.pieces)
    find = re.compile(" +[^ \n]*|\n[^ \n]*" if bare else " +[^ ]*").findall

    def split(text: str | None) -> list[str]:
        if not text:
            return []
        if SPACE_MARK in text:
            text = text.replace(SPACE_MARK, " ")
        if "  " in text or text[0] == " ":
            return [c.removeprefix(" ") for c in find(" " + text)]
        return text.replace("\n", " \n").split(" ") if bare else text.split(" ")

    return split


def cutter(table: PieceTable):
    """list of chunks -> (list of all their units, array of the number of units of each): with its mark, a chunk is cut between
    two characters that stand side by side in no piece, where no edge can cross."""
    places = {c: i + 1 for i, c in enumerate(sorted({c for p in table.pieces if len(p) > 1 for c in p}))}
    wide = len(places) + 1
    place, inside = np.zeros(0x110000, np.int64), np.zeros(wide * wide, bool)
    place[[ord(c) for c in places]] = list(places.values())
    inside[[places[p[i]] * wide + places[p[i + 1]] for p in table.pieces for i in range(len(p) - 1)]] = True
    bare = not any("\n" in p for p in table.pieces)

    def cut(chunks: list[str]) -> tuple[list[str], np.ndarray]:
        if not chunks:
            return [], np.zeros(0, int)
        marked = [c if bare and c[:1] == "\n" else SPACE_MARK + c for c in chunks]
        text, heads = "".join(marked).replace(" ", SPACE_MARK), np.r_[0, np.cumsum(list(map(len, marked)))]
        at = place[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)]
        begins = np.r_[True, ~inside[at[:-1] * wide + at[1:]]]
        begins[heads[:-1]] = True
        cuts = np.flatnonzero(begins)
        units = [text[a:b] for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(text)], strict=True)]
        return units, np.diff(np.searchsorted(cuts, heads))

    return cut
