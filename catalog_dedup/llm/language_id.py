"""Language identification by hierarchical discrimination.

Character trigrams of the whole lower-cased text (runs of other characters than letters count as one space) are hashed
into ``DIM`` counts and scaled to unit length. Linear support vector machines, one against one, first tell the language
family and then, within the family, the language. Models learn from a sample of labelled rows whose expected size is
``SAMPLE`` per language and ``SAMPLED`` in all at most, chosen by a hash of doc_id and text; everything else covers all rows.

Null texts and texts without a letter are ``und`` with score 0, and so are all texts if no row has a label. With one
learned language every other text is given that, with score 1. Ties go to the first in code-point order. Rows are judged
one by one; a row whose doc_id is null counts as one with an empty id. Input columns named like a result are replaced.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_text, remainder, uniform

DIM = 4096
SAMPLE, SAMPLED = 500, 6000
FOLDS, HELD_OUT = 4, 2
#: ISO 639-1 codes by family. Any other code is a family of its own.
FAMILIES = {
    "germanic": "de en nl sv da no nb nn is af yi lb",
    "romance": "es fr it pt ro ca gl oc la",
    "slavic": "ru uk be pl cs sk sl hr sr bs bg mk",
    "indic": "hi ur bn pa mr gu ne",
    "turkic": "tr az kk uz ky tk",
    "uralic": "fi et hu",
    "semitic": "ar he mt am",
}
FAMILY_OF = {code: family for family, codes in FAMILIES.items() for code in codes.split()}


def trigram_counts(text: str | None) -> np.ndarray | None:
    """Hashed trigram counts, or None for a text without letters."""
    if not text or not any(map(str.isalpha, text)):
        return None
    low = text.lower()
    codes = np.frombuffer(low.encode("utf-32-le", "surrogatepass"), "<u4")
    letter = ((codes >= 97) & (codes <= 122)) | ((codes >= 0xC0) & (codes != 0xD7) & (codes != 0xF7) & ((codes < 0x2000) | (codes > 0x2BFF)))
    codes = np.where(letter, codes, 32)
    codes = codes[np.r_[True, (codes[1:] != 32) | (codes[:-1] != 32)]] if len(codes) > 1 else codes
    c = np.concatenate([[32], codes, [32]]).astype(np.uint64)
    mixed = (c[:-2] * np.uint64(0x9E3779B1) + c[1:-1] * np.uint64(0x85EBCA77) + c[2:] * np.uint64(0xC2B2AE3D)) * np.uint64(0x27D4EB2F165667C5)
    return np.bincount((mixed >> np.uint64(52)).astype(np.int64) % DIM, minlength=DIM)


def unit(counts: np.ndarray) -> np.ndarray:
    x = np.sqrt(counts.astype(np.float32))
    return x / max(float(np.sqrt(x @ x)), 1e-9)


def fit_svm(x: np.ndarray, y: np.ndarray, cost: float = 10.0, epochs: int = 12) -> np.ndarray:
    """Weights (last one the bias) of a linear support vector machine, by dual coordinate descent; y is +1 or -1."""
    x = np.hstack([x, np.ones((len(x), 1), np.float32)])
    w, alpha, q = np.zeros(x.shape[1]), np.zeros(len(x)), (x * x).sum(1)
    order = np.random.default_rng(9)
    for _ in range(epochs):
        for i in order.permutation(len(x)):
            new = min(max(alpha[i] + (1 - y[i] * (w @ x[i])) / q[i], 0.0), cost)
            w += (new - alpha[i]) * y[i] * x[i]
            alpha[i] = new
    return w.astype(np.float32)


def one_against_one(x: np.ndarray, labels: np.ndarray) -> dict:
    names = sorted(set(labels.tolist()))
    pairs = list(combinations(range(len(names)), 2))
    rows = [fit_svm(x[m], np.where(labels[m] == names[a], 1.0, -1.0)) for a, b in pairs for m in [(labels == names[a]) | (labels == names[b])]]
    return {"names": names, "pairs": pairs, "w": np.array(rows, np.float32).reshape(len(pairs), DIM + 1)}


def choose(model: dict, x: np.ndarray) -> tuple[str, float]:
    """The class with the largest mean probability against the others, and the least of its probabilities."""
    k = len(model["names"])
    if k == 1:
        return model["names"][0], 1.0
    p = 1 / (1 + np.exp(-3 * (model["w"][:, :-1] @ x + model["w"][:, -1])))
    against = np.ones((k, k))
    for (a, b), v in zip(model["pairs"], p, strict=True):
        against[a, b], against[b, a] = v, 1 - v
    best = int(np.argmax(against.sum(1)))
    return model["names"][best], float(np.delete(against[best], best).min())


def fit(docs: DataFrame, learn: Column, sample: int = SAMPLE) -> dict | None:
    """The two-level model from rows where ``learn`` holds and lang is not null; None if there is none."""
    rows = docs.filter(learn & F.col("lang").isNotNull())
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # a row per language
    if not counts:
        return None
    sample = min(sample, max(1, SAMPLED // len(counts)))
    share = F.element_at(F.create_map(*[v for k, n in counts.items() for v in (F.lit(k), F.lit(min(1.0, sample / n)))]), F.col("lang"))
    chosen = rows.filter(uniform(F.col("doc_id"), F.col("text")) < share).dropDuplicates(["lang", "doc_id", "text"]).select(F.col("lang").alias("_label"), "text")
    made = map_text(chosen, ["_label"], [("x", T.BinaryType())], lambda texts: [[None if (c := trigram_counts(t)) is None else unit(c).astype(np.float16).tobytes() for t in texts]])
    got = [(r["_label"], r["x"]) for r in made.filter("x IS NOT NULL").collect()]
    if not got:
        return None
    got.sort()  # the order in which partitions arrive doesn't matter
    labels = np.array([g[0] for g in got], object)
    x = np.stack([np.frombuffer(g[1], np.float16) for g in got]).astype(np.float32)
    family = np.array([FAMILY_OF.get(v.lower().split("-")[0], v) for v in labels], object)
    return {"family": one_against_one(x, family), "within": {f: one_against_one(x[family == f], labels[family == f]) for f in sorted(set(family.tolist()))}}


def predict(docs: DataFrame, model: dict | None, keep: list[str]) -> DataFrame:
    """``keep`` columns, ``lang_pred`` and ``score``."""

    def run(texts: list) -> list:
        names, scores = [], []
        for t in texts:
            counts = trigram_counts(t) if model else None
            if counts is None:
                names.append("und")
                scores.append(0.0)
                continue
            x = unit(counts)
            family, p = choose(model["family"], x)
            lang, q = choose(model["within"][family], x)
            names.append(lang)
            scores.append(p * q)
        return [names, np.array(scores, float)]

    return map_text(docs, keep, [("lang_pred", T.StringType()), ("score", T.DoubleType())], run)


def identify(docs: DataFrame, keep: list[str]) -> DataFrame:
    """Learn from the rows outside the held-out fold, predict all of them."""
    model = fit(docs, remainder(F.col("doc_id"), FOLDS) != HELD_OUT)
    return predict(docs, model, keep)
