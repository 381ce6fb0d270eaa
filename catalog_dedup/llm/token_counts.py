"""Token counts by dynamic programming over a trie.

The distinct pre-tokens that a task meets are inserted in a trie. A node stands for a prefix and holds the best score and
the number of tokens of the best unigram segmentation of that prefix, computed once however many pre-tokens share it;
where a pre-token ends, its count is stored. A document's count is the sum over its pre-tokens. Nothing is shuffled: a
task keeps its own trie, and starts anew beyond ``NODES`` nodes, which bounds its memory and changes no count.

Pre-tokens of over ``LONG`` characters would fill the trie with nodes that nothing shares, so theirs are let go at once: the same
recurrence keeps the last pieces' scores only. As in ``lattice``, the file's pieces and scores are read as a unigram lexicon whatever
model it was made for.

Of equally good segmentations the one with the longer last piece counts. A character that is no piece counts as many tokens
as it has UTF-8 bytes (one where the table has no byte pieces). Null and empty texts have 0 tokens. Rows are counted one by
one; an empty table gives no rows. Input columns named like a result are replaced.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import map_text
from .pieces import PieceTable, splitter

NODES, LONG = 600_000, 4096


class ForwardTrie:
    """Prefixes of pre-tokens with forward scores and token counts."""

    def __init__(self, table: PieceTable, nodes: int = NODES):
        self.table, self.most = table, nodes
        self.clear()

    def clear(self) -> None:
        self.child: dict[tuple[int, str], int] = {}
        self.score, self.tokens = [0.0], [0]
        self.terminal: dict[str, int] = {}

    def count(self, word: str) -> int:
        """Tokens of the best segmentation of ``word``, which is inserted if it is new."""
        known = self.terminal.get(word)
        if known is not None:
            return known
        if len(word) > LONG:
            return self.count_long(word)
        if len(self.score) > self.most:
            self.clear()
        pieces, longest, child, score, tokens = self.table.pieces, self.table.longest, self.child, self.score, self.tokens
        path = [0]
        node = 0
        for end, c in enumerate(word, 1):
            below = child.get((node, c))
            if below is None:
                best, n = -np.inf, 0
                for start in range(max(0, end - longest), end):
                    hit = pieces.get(word[start:end])
                    if hit and score[path[start]] + hit[1] > best:
                        best, n = score[path[start]] + hit[1], tokens[path[start]] + 1
                if c not in pieces and score[node] + self.table.unknown > best:
                    best = score[node] + self.table.unknown
                    n = tokens[node] + (len(c.encode("utf-8", "surrogatepass")) if self.table.bytes_from >= 0 else 1)
                below = child[node, c] = len(score)
                score.append(best)
                tokens.append(n)
            path.append(below)
            node = below
        self.terminal[word] = tokens[node]
        return tokens[node]

    def count_long(self, word: str) -> int:
        """The same without a node; scores and counts of the last ``longest`` prefixes are at hand."""
        pieces, longest = self.table.pieces, self.table.longest
        score, tokens = [0.0] * (longest + 1), [0] * (longest + 1)
        for end, c in enumerate(word, 1):
            best, n = -np.inf, 0
            for start in range(max(0, end - longest), end):
                hit = pieces.get(word[start:end])
                at = start % (longest + 1)
                if hit and score[at] + hit[1] > best:
                    best, n = score[at] + hit[1], tokens[at] + 1
            at = (end - 1) % (longest + 1)
            if c not in pieces and score[at] + self.table.unknown > best:
                best, n = score[at] + self.table.unknown, tokens[at] + (len(c.encode("utf-8", "surrogatepass")) if self.table.bytes_from >= 0 else 1)
            score[end % (longest + 1)], tokens[end % (longest + 1)] = best, n
        return tokens[len(word) % (longest + 1)]


def count_tokens(docs: DataFrame, table: PieceTable, keep: list[str]) -> DataFrame:
    """``keep`` columns, ``n_pre_tokens`` and ``n_tokens`` of every row."""
    trie: list[ForwardTrie] = []

    def run(texts: list) -> list:
        if not trie:
            trie.append(ForwardTrie(table))
        split, seen, count = splitter(table), trie[0].terminal, trie[0].count
        totals, words = np.zeros(len(texts), np.int64), np.zeros(len(texts), np.int64)
        for k, t in enumerate(texts):
            parts = split(t)
            words[k] = len(parts)
            n = 0
            for w in parts:
                n += seen[w] if w in seen else count(w)
            totals[k] = n
            seen = trie[0].terminal  # a new dictionary after clear()
        return [words, totals]

    return map_text(docs, keep, [("n_pre_tokens", T.LongType()), ("n_tokens", T.LongType())], run)
