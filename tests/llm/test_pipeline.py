"""The pipeline, stage by stage, against brute force on the smallest documents."""

import duckdb
import pytest

pytest.importorskip("corpus_pipeline")

import corpus_pipeline  # noqa: E402
from catalog_dedup.llm import language_id, mixing, oracles, pieces  # noqa: E402
from catalog_dedup.llm.common import remainder, stash  # noqa: E402
from catalog_dedup.llm.queries import piece_table  # noqa: E402

from .test_near_copies import roots_of  # noqa: E402
from .test_operators import best_path  # noqa: E402

SF = "/root/testdata/sf0.001"


def keys(rows):
    return sorted((r.doc_id, r.text, r.source) for r in rows)


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["language ID", "quality rules", "SimHash near-dedup", "mixing sources to target weights", "SentencePiece encoding"]

    # Language: the model's classes one text at a time.
    from pyspark.sql import functions as F

    model = language_id.fit(docs, remainder(F.col("doc_id"), language_id.FOLDS) != language_id.HELD_OUT)
    before = docs.collect()
    docs = stash(stages["language ID"](spark, docs, SF), "t")

    def stays(text):
        c = language_id.trigram_counts(text)
        if c is None:
            return False
        x = language_id.unit(c)
        family, p = language_id.choose(model["family"], x)
        return p * language_id.choose(model["within"][family], x)[1] >= corpus_pipeline.LEAST_LANGUAGE_SCORE

    assert docs.columns == columns and keys(docs.collect()) == keys([r for r in before if stays(r.text)])

    # Rules: their SQL.
    frame = docs.toPandas()  # read by DuckDB under its name
    judged = duckdb.connect()
    judged.register("frame", frame)
    want = judged.execute(f"WITH {oracles.verdict_sql('frame')} SELECT doc_id FROM judged WHERE kept ORDER BY 1").fetchall()
    docs = stash(stages["quality rules"](spark, docs, SF), "t")
    assert docs.columns == columns and sorted(r.doc_id for r in docs.collect()) == [w[0] for w in want]

    # Near-duplicates: all pairs.
    before = sorted(docs.collect(), key=lambda r: r.doc_id)
    stay = set(roots_of([(r.doc_id, r.text) for r in before]))
    docs = stash(stages["SimHash near-dedup"](spark, docs, SF), "t")
    assert docs.columns == columns and keys(docs.collect()) == keys([r for r in before if r.doc_id in stay])

    # Mixing: words of every source against targets worked out one by one.
    before = docs.collect()
    size = {}
    for r in before:
        size[r.source] = size.get(r.source, 0) + len(r.text.split())
    weight = {s: (3, 1, 2)[k % 3] for k, s in enumerate(sorted(size))}
    target, free, left = {}, set(size), 1.5 * sum(size.values())
    while True:
        rate = left / sum(weight[s] for s in free)
        over = {s for s in free if rate * weight[s] > 2 * size[s]}
        if not over:
            break
        for s in over:
            target[s] = 2.0 * size[s]
            left -= target[s]
        free -= over
    target |= {s: rate * weight[s] for s in free}
    mixed = stash(stages["mixing sources to target weights"](spark, docs, SF), "t")
    after = mixed.collect()
    assert mixed.columns == columns
    whole = {r.doc_id: r.text for r in before}
    for s in size:
        mine = [r for r in after if r.source == s]
        assert abs(sum(len(r.text.split()) for r in mine) - target[s]) <= 2
        assert sum(r.text != whole[r.doc_id] for r in mine) <= 1 and max(sum(x.doc_id == r.doc_id for x in mine) for r in mine) <= 2

    # Pieces: best paths one text at a time.
    table = piece_table()
    split, known = pieces.splitter(table), {}

    def ids(text):
        return [i for w in split(text) for i in known.setdefault(w, best_path(w, table) if w not in known else None)]

    coded = stages["SentencePiece encoding"](spark, mixed, SF).collect()
    assert sorted((r.doc_id, list(r.ids)) for r in coded) == sorted((r.doc_id, ids(r.text)) for r in after) and all(r.round_trip for r in coded)


def test_run_gives_what_the_stages_give(spark):
    out = corpus_pipeline.run(spark, SF)
    assert out.columns == ["doc_id", "lang", "source", "n_tokens", "ids", "round_trip"] and out.filter("NOT round_trip").isEmpty() and out.count() > 100
    assert mixing.MOST == 2
