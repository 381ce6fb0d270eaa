"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics come from the whole text alone. Trees grow on the driver from histograms of binned features of a labelled
sample of at most about ``SAMPLE`` labels (chosen by a hash of doc_id) and twice as many rows, are flattened into arrays of one complete binary
tree each, and are walked for a whole batch at once with numpy.

Null texts count as empty, and empty texts get a score like any other. Without labels every score is 0.5, with labels of
one class their smoothed share. Rows are scored one by one; a null doc_id counts as an empty id. Labels that are null
are left out. Input columns named like a result are replaced. An empty table gives no rows.
"""

from __future__ import annotations

from operator import eq

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_text, remainder, uniform

SAMPLE = 20_000
FOLDS, HELD_OUT = 3, 1
BINS, TREES, DEPTH, RATE, L2 = 64, 60, 4, 0.15, 1.0
FEATURES = (
    "words", "word_length", "distinct_words", "distinct_pairs", "stutters", "lines", "distinct_lines", "capitals", "digits", "symbols",
    "exclamations", "stops", "other_marks", "bars", "letters", "longest_word", "title_words",
)
#: Character classes: 0 other, 1 capital, 2 digit, 3 symbol, 4 exclamation or question mark, 5 full stop or comma, 6 other mark, 7 bar, 8 small letter.
_CLASS = np.zeros(0x250, np.uint8)
for _c in range(0x250):
    _s = chr(_c)
    _CLASS[_c] = 7 if _s == "|" else 3 if _s in "#*$%&<>@^~=+_" else 4 if _s in "!?" else 5 if _s in ".," else 2 if _s.isdigit() else 1 if _s.isupper() else 8 if _s.isalpha() else 6 if not _s.isspace() and _s.isprintable() else 0


def statistics(text: str | None) -> list[float]:
    """The features of one whole text, in the order of FEATURES."""
    text = text or ""
    words = text.split()
    n = max(len(words), 1)
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    kinds = np.bincount(_CLASS[np.minimum(codes, 0x24F)], minlength=9)
    chars = max(len(text), 1)
    lines = [x for x in text.split("\n") if x and not x.isspace()]
    lengths = list(map(len, words))
    return [
        float(len(words)), sum(lengths) / n, len(set(words)) / n, len(set(zip(words, words[1:]))) / n, sum(map(eq, words, words[1:])) / n,
        len(lines) / n, len(set(lines)) / max(len(lines), 1), kinds[1] / chars, kinds[2] / chars, kinds[3] / n, kinds[4] / n, kinds[5] / n,
        kinds[6] / n, kinds[7] / n, kinds[8] / chars, float(max(lengths, default=0)), sum(map(str.istitle, words)) / n,
    ]


def fit_trees(x: np.ndarray, y: np.ndarray) -> dict:
    """Boosted trees as arrays: feature and cut of every inner node (trees x 2^DEPTH - 1), value of every leaf."""
    prior = (y.sum() + 1) / (len(y) + 2)
    base = float(np.log(prior / (1 - prior)))
    inner, leaves = 2**DEPTH - 1, 2**DEPTH
    model = {"base": base, "feature": np.zeros((TREES, inner), np.int32), "cut": np.full((TREES, inner), np.inf), "value": np.zeros((TREES, leaves))}
    if len(y) == 0 or y.min() == y.max():
        return model | {k: model[k][:0] for k in ("feature", "cut", "value")}
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, BINS + 1)[1:-1])) for f in range(x.shape[1])]
    binned = np.stack([np.searchsorted(e, x[:, f], "left") for f, e in enumerate(edges)], 1)  # bin <= k iff x <= edge k
    raw = np.full(len(y), base)
    for t in range(TREES):
        p = 1 / (1 + np.exp(-raw))
        grad, hess = y - p, p * (1 - p)
        node = np.zeros(len(y), np.int64)
        for level in range(DEPTH):
            k, first = 2**level, 2**level - 1
            best, feature, cut_bin = np.full(k, 1e-6), np.zeros(k, np.int64), np.full(k, BINS)
            for f in range(x.shape[1]):
                at = node * BINS + binned[:, f]
                g = np.bincount(at, grad, k * BINS).reshape(k, BINS).cumsum(1)
                h = np.bincount(at, hess, k * BINS).reshape(k, BINS).cumsum(1)
                gt, ht = g[:, -1:], h[:, -1:]
                gain = g**2 / (h + L2) + (gt - g) ** 2 / (ht - h + L2) - gt**2 / (ht + L2)
                gain[(h < 1) | (ht - h < 1)] = 0
                b = gain[:, : len(edges[f])].argmax(1) if len(edges[f]) else np.zeros(k, int)
                v = gain[np.arange(k), b] if len(edges[f]) else np.zeros(k)
                won = v > best
                best[won], feature[won], cut_bin[won] = v[won], f, b[won]
            split = cut_bin < BINS
            model["feature"][t, first : first + k] = feature
            model["cut"][t, first : first + k] = [edges[f][b] if s else np.inf for f, b, s in zip(feature, cut_bin, split, strict=True)]
            node = 2 * node + (binned[np.arange(len(y)), feature[node]] > cut_bin[node])
        g, h = np.bincount(node, grad, leaves), np.bincount(node, hess, leaves)
        model["value"][t] = RATE * g / (h + L2)
        raw += model["value"][t][node]
    return model


def walk(model: dict, x: np.ndarray) -> np.ndarray:
    """Scores of a batch: every row steps down every tree at once."""
    raw = np.full(len(x), model["base"])
    trees = np.arange(len(model["feature"]))
    if len(trees) and len(x):
        at = np.zeros((len(x), len(trees)), np.int64)
        for _ in range(DEPTH):
            at = 2 * at + 1 + (np.take_along_axis(x, model["feature"][trees, at], 1) > model["cut"][trees, at])
        raw += model["value"][trees, at - (2**DEPTH - 1)].sum(1)
    return 1 / (1 + np.exp(-raw))


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> dict:
    """The model from labelled rows outside the held-out fold."""
    known = labels.filter(F.col("quality").isNotNull() & (remainder(F.col("doc_id"), FOLDS) != HELD_OUT)).select(F.col("doc_id").alias("_id"), F.col("quality").alias("_label"))
    n = known.count()
    chosen = F.broadcast(known.filter(uniform(F.col("_id")) < min(1.0, sample / max(n, 1))))  # about `sample` rows at most
    rows = docs.select("doc_id", "text").join(chosen, F.col("doc_id") == F.col("_id")).select("_id", "_label", "text")
    # An id may stand in many rows: repeated ones count once, and of too many different ones a share is drawn.
    met = rows.count()
    rows = rows.filter(uniform(F.col("_id"), F.col("text")) < min(1.0, 2 * sample / max(met, 1))).dropDuplicates(["_id", "_label", "text"])
    made = map_text(rows, ["_label"], [("x", T.ArrayType(T.DoubleType()))], lambda texts: [[statistics(t) for t in texts]])
    got = sorted((r["_label"], tuple(r["x"])) for r in made.collect())
    y = np.array([g[0] for g in got], float)
    return fit_trees(np.array([g[1] for g in got], float).reshape(len(got), len(FEATURES)), y)


def score(docs: DataFrame, model: dict, keep: list[str]) -> DataFrame:
    """``keep`` columns, ``score`` (likelihood of label 1) and ``predicted``."""

    def run(texts: list) -> list:
        s = walk(model, np.array([statistics(t) for t in texts], float).reshape(len(texts), len(FEATURES)))
        return [s, (s >= 0.5).astype(np.int32)]

    return map_text(docs, keep, [("score", T.DoubleType()), ("predicted", T.IntegerType())], run)
