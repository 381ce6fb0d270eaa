"""Each operator against brute force on small tables with nulls, empties, repeats, long texts and clashing columns."""

import zlib

import numpy as np
import pytest

sp = pytest.importorskip("sentencepiece")

import public_tokenizers  # noqa: E402

from catalog_dedup.llm import common, language_id, lattice, mixing, nn_descent, pieces, quality_classifier, quality_rules, simhash, token_counts, token_output, url_filters  # noqa: E402

WORDS = "the of and reingth onhe tionat, erblewh heon. Edor ñgaó über çè 東京 x1 !!! foo_bar".split()


def corpus(n=240):
    r = np.random.default_rng(3)
    out = []
    for i in range(n):
        words = [WORDS[k] for k in r.integers(0, len(WORDS), 40 + i % 50)]
        out.append((i, " ".join(words).replace(" of ", "\n", 2), ("en", "de", "fr", None)[i % 4], ("a", "b", None)[i % 3], 7, "kept", 1.5))
    out += [(n, None, "en", "a", 0, "x", None), (n + 1, "", "de", None, 0, "x", None), (n + 2, " \n\t ", None, "b", 0, "x", None), (5, out[5][1], "fr", "c", 1, "y", 2.0), (n + 3, "Supercalifragilistic" * 40, "en", "a", 1, "x", 0.0), (n + 4, "long " * 9000, "en", "b", 1, "x", 0.0)]
    return out


SCHEMA = "doc_id long, text string, lang string, source string, n_words int, kept string, score double"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(corpus(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def table():
    return pieces.load(public_tokenizers.path("piece_bpe_32k.model"))


def test_rules(docs, none):
    got = {(r.doc_id, r.lang): r for r in quality_rules.apply_rules(docs, ["doc_id", "lang", "n_words"]).collect()}
    assert len(got) == len(corpus())
    for d, text, lang, *_ in corpus():
        w = (text or "").split()
        runs = [" ".join(w[i : i + 8]) for i in range(len(w) - 7)]
        twice = {k for i, x in enumerate(runs) if runs.count(x) > 1 for k in range(i, i + 8)} if len(w) < 1000 else set(range(len(w)))
        r = got[d, lang]
        assert (r.n_words, r.word_chars, r.n_repeat_words) == (len(w), sum(map(len, w)), len(twice))
        assert r.base_failed == (len(w) < 20 or 100 * len(twice) > 30 * len(w)) and not (r.base_failed and r.kept)
    assert quality_rules.apply_rules(none, ["doc_id"]).count() == 0


def test_sketch_quantiles_are_close(spark):
    v = np.random.default_rng(0).integers(0, 100_000, 5000)
    from pyspark.sql import functions as F

    b = np.array([r.b for r in spark.createDataFrame([(int(x),) for x in v], "v long").select(quality_rules.bucket(F.col("v")).alias("b")).collect()])
    assert abs(np.sort(b)[2500] / np.median(v) - 1) < 1 / 32


def test_fingerprints_and_components(spark, docs, none):
    from xxhash import xxh64_intdigest

    def slow(t):
        w = (t or "").encode().lower().split()
        s = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([b" ".join(w)] if w else [])
        h = [xxh64_intdigest(x, 42) for x in s]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    got = simhash.duplicate_classes(docs).collect()
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    want = {d: slow(t) for d, t, *_ in corpus()}
    assert all(int(x.fingerprint, 16) == want[d] for d, rows in by.items() for x in rows)
    ids = sorted(want)
    root = {i: i for i in ids}
    moved = True
    while moved:
        moved = False
        for a in ids:
            for b in ids:
                if (want[a] ^ want[b]).bit_count() <= 2 and root[a] != root[b]:
                    root[a] = root[b] = min(root[a], root[b])
                    moved = True
    assert all(x.component_id == root[d] for d, rows in by.items() for x in rows)
    assert simhash.duplicate_classes(none).count() == 0
    assert sorted(r.doc_id for r in simhash.one_of_each(docs).collect()) == sorted(set(root.values()))


def test_crowded_bins_are_exact(spark, monkeypatch):
    r = np.random.default_rng(1)
    fps = [int(x) for x in np.unique(np.r_[r.integers(0, 2**62, 50), [sum(1 << int(b) for b in r.choice(12, 4)) for _ in range(400)]])]
    nodes = spark.createDataFrame([(x,) for x in fps], "fp long")

    def roots():
        return {x.node: x.root for x in simhash.components(simhash.links(nodes)).collect()}

    plain = roots()
    monkeypatch.setattr(simhash, "BIN", 2)
    assert roots() == plain


def test_pivots_discard_no_link():
    r = np.random.default_rng(0)
    x = r.integers(0, 2**64, 200, dtype=np.uint64)
    x = np.r_[x, x[:50] ^ np.uint64(5)]
    a, b = simhash.linked_pairs(x, simhash.pivot_table(x))
    i, j = np.triu_indices(len(x), 1)
    near = np.bitwise_count(x[i] ^ x[j]) <= 2
    assert set(zip(a, b)) == set(zip(i[near], j[near]))


def test_mix_meets_targets(docs, none):
    rows = mixing.mix_sizes(docs).collect()
    assert len(rows) == len(corpus())
    by = {}
    for r in rows:
        by.setdefault(r.source, []).append(r)
        assert 0 <= r.taken <= 2 * r.size
    total = sum(r.size for r in rows)
    assert abs(sum(b[0].target for b in by.values()) - 1.5 * total) < 1e-6 * total
    for b in by.values():
        assert abs(sum(r.taken for r in b) - b[0].target) <= 2 and b[0].target <= 2 * b[0].source_size
    again = {(r.doc_id, r.source): r.taken for r in mixing.mix_sizes(docs).collect()}
    assert again == {(r.doc_id, r.source): r.taken for r in rows}
    words = sum(len(r.text.split()) for r in mixing.mix(docs).collect())
    assert words == sum(r.taken for r in rows)
    assert mixing.mix_sizes(none).count() == 0 and mixing.mix(none).count() == 0


def test_language(spark, docs, none):
    text = {"en": "the heon onhe of and with", "de": "und der schei über nicht ein", "fr": "les éau leçon de la pour", "es": "el ción los que ñue para"}
    rows = [(i, " ".join(np.random.default_rng(i).permutation(text[k].split() * 5)), k, "s", 0, "x", 0.0) for i in range(200) for k in [sorted(text)[i % 4]]]
    rows += [(900, None, "en", "s", 0, "x", 0.0), (901, "123 !!", "en", "s", 0, "x", 0.0)]
    got = {r.doc_id: r for r in language_id.identify(spark.createDataFrame(rows, SCHEMA), ["doc_id", "score"]).collect()}
    assert all(got[i].lang_pred == k and 0 <= got[i].score <= 1 for i, _, k, *_ in rows[:200])
    assert got[900].lang_pred == got[901].lang_pred == "und"
    assert language_id.identify(none, ["doc_id"]).count() == 0


def test_trees(spark, docs, none):
    r = np.random.default_rng(0)
    x = r.normal(size=(2000, len(quality_classifier.FEATURES)))
    y = ((x[:, 2] > 0.3) ^ (x[:, 5] < -0.2)).astype(float)
    m = quality_classifier.fit_trees(x, y)
    p = quality_classifier.walk(m, x)
    assert ((p > 0.5) == y).mean() > 0.95
    for k in range(20):  # one row and one tree at a time
        raw = m["base"]
        for t in range(len(m["feature"])):
            node = 0
            for _ in range(quality_classifier.DEPTH):
                node = 2 * node + 1 + int(x[k, m["feature"][t, node]] > m["cut"][t, node])
            raw += m["value"][t, node - 2**quality_classifier.DEPTH + 1]
        assert np.isclose(1 / (1 + np.exp(-raw)), p[k])
    labels = spark.createDataFrame([(i, i % 2) for i in range(100)] + [(7, None)], "doc_id long, quality int")
    model = quality_classifier.fit(docs, labels)
    assert quality_classifier.score(docs, model, ["doc_id", "score"]).filter("score BETWEEN 0 AND 1").count() == len(corpus())
    assert quality_classifier.score(none, quality_classifier.fit(none, labels.limit(0)), ["doc_id"]).count() == 0


def test_urls(spark):
    rules = spark.createDataFrame([("com", "/", "allow"), ("example.com", "/en/", "block"), ("WWW.example.com", "/en/", "allow"), ("net", "/es/", "block")], "host string, path string, verdict string")
    urls = ["http://a.Example.COM/en/x", "https://www.example.com/en/", "http://com/x?y", "http://example.com", "x", None, "ftp://z.net/es/1#2", "http://notexample.com/en/", "http://net/es", "http://a.net/ES/", "http://a.net/es/?q=://b.com/"]
    pages = spark.createDataFrame([(i, u, "v") for i, u in enumerate(urls)] + [(0, urls[0], "w")], "page_id long, url string, verdict string")
    got = {}
    for r in url_filters.judge(pages, rules, ["page_id", "verdict"]).collect():
        got.setdefault(r.page_id, []).append((r.host, r.path, r.rule, r.verdict))
    assert got[0] == [("a.example.com", "/en/x", "example.com/en/", "block")] * 2
    assert got[1][0][2:] == ("www.example.com/en/", "allow") and got[2][0] == ("com", "/x", "com/", "allow") and got[3][0] == ("example.com", "", None, "allow")
    assert got[4][0] == ("", "", None, "allow") == got[5][0] and got[6][0] == ("z.net", "/es/1", "net/es/", "block") and got[7][0][2] == "com/"
    assert got[8][0][2] is None and got[9][0][2] is None and got[10][0][2] == "net/es/"
    assert url_filters.judge(pages, rules.limit(0), ["page_id"]).filter("rule IS NOT NULL").count() == 0
    h = np.arange(1000) * 7919 - 400000
    bloom = url_filters.blocked_bloom(h)
    assert url_filters.possible(bloom, h).all() and url_filters.possible(bloom, np.arange(10**6, 2 * 10**6)).mean() < 0.02


def best_path(word, table):
    best = [(0.0, [])] + [None] * len(word)
    for e in range(1, len(word) + 1):
        for s in range(max(0, e - table.longest), e):
            hit = table.pieces.get(word[s:e])
            step = (hit[1], [hit[0]]) if hit else (table.unknown, [table.bytes_from + b for b in word[s:e].encode()]) if e - s == 1 else None
            if step and (best[e] is None or best[s][0] + step[0] > best[e][0]):
                best[e] = (best[s][0] + step[0], best[s][1] + step[1])
    return best[-1][1]


def test_lattice_and_trie_equal_brute_force(docs, none, table, monkeypatch):
    split = pieces.splitter(table)
    want = sorted([i for w in split(t) for i in best_path(w, table)] for _, t, *_ in corpus())
    got = lattice.encode(docs, table, ["doc_id", "n_words"]).collect()
    assert sorted(list(r.ids) for r in got) == want and all(r.round_trip for r in got)
    counts = token_counts.count_tokens(docs, table, ["doc_id"]).collect()
    assert sorted(r.n_tokens for r in counts) == sorted(map(len, want))
    monkeypatch.setattr(lattice, "HEAD", 3)
    monkeypatch.setattr(token_counts, "NODES", 10)
    rare = lattice.encode(docs, table, ["doc_id"]).collect()
    assert sorted(list(r.ids) for r in rare) == want and all(r.round_trip for r in rare)
    assert sorted(r.n_tokens for r in token_counts.count_tokens(docs, table, ["doc_id"]).collect()) == sorted(map(len, want))
    back = {r.doc_id: r.text for r in lattice.decode(lattice.encode(docs, table, ["doc_id"]), table, ["doc_id"]).collect()}
    assert all(back[d] == (t or "") for d, t, *_ in corpus())
    assert lattice.encode(none, table, ["doc_id"]).count() == 0 and token_counts.count_tokens(none, table, ["doc_id"]).count() == 0


def test_runs_of_spaces_equal_brute_force_over_the_whole_file(spark, table, monkeypatch):
    from dataclasses import replace

    m = sp.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    every = {m.id_to_piece(i): (i, m.get_score(i)) for i in range(m.vocab_size()) if not (m.is_byte(i) or m.is_control(i) or m.is_unknown(i) or m.is_unused(i))}
    full = replace(table, pieces=every, longest=max(map(len, every)), unknown=min(s for _, s in every.values()) - 10)
    texts = ["a" + " " * 16 + "the end", "        return value", "if x:\n        return value", " ", "a ", "  a", "a  \n  b \n", "\n  \n", " " * 37 + "東  京", "tab \t  x", "x" + " " * 200 + "y", "a  b c   d", "the  the   the"]
    want = [best_path(("▁" + t).replace(" ", "▁"), full) for t in texts]  # whole texts, cut nowhere
    assert list(map(len, want[:2])) == [5, 6]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for head in (lattice.HEAD, 3):
        monkeypatch.setattr(lattice, "HEAD", head)
        got = {r.doc_id: r for r in lattice.encode(rows, table, ["doc_id"]).collect()}
        assert [list(got[i].ids) for i in range(len(texts))] == want and all(r.round_trip for r in got.values())
    counts = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(rows, table, ["doc_id"]).collect()}
    assert [counts[i] for i in range(len(texts))] == list(map(len, want))
    marks = spark.createDataFrame([(0, "a▁ ▁b"), (1, "▁▁ a")], "doc_id long, text string")  # marks in the text count as spaces
    got = {r.doc_id: list(r.ids) for r in lattice.encode(marks, table, ["doc_id"]).collect()}
    assert got == {0: best_path("▁a▁▁▁b", full), 1: best_path("▁▁▁▁a", full)}


def test_shards(docs, none):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    m = token_output.write_shards(docs, path)
    got = token_output.read_shards(m).orderBy("start").collect()
    rows = sorted(corpus(), key=lambda r: r[0])
    assert [r.doc_id for r in got] == [r[0] for r in rows]
    at = 0
    for r, row in zip(got, rows):
        ids = np.frombuffer(r.ids, "<u4").tolist()
        assert ids == tok.encode(row[1] or "", add_special_tokens=False).ids + [1] and (r.start, r.n_tokens) == (at, len(ids))
        at += len(ids)
    crc = {r.start: r.ids_crc32 for r in token_output.read_shards(m, digest=True).collect()}
    assert all(crc[r.start] == zlib.crc32(r.ids) for r in got)
    assert token_output.read_shards(token_output.write_shards(none, path)).count() == 0


@pytest.mark.parametrize("text", ["It's THE end...,, don't", "a<|endoftext|>b <|startoftext|>", "İstanbul ΣΑΣ été ñ,", "tab\tx\x0by\x0cz q r", "№ ½ ²³ 1234,5.6", "Straße. ÀÉÎ, ŉ ǅ"])
def test_words_are_tokenized_as_in_whole_texts(text):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    want = Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids
    assert np.frombuffer(token_output.word_tokenizer(path)([text])[0], "<u4").tolist() == want


def test_words_of_all_latin_letters_are_tokenized_as_in_whole_texts():
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    tok, mine = Tokenizer.from_file(path), token_output.word_tokenizer(path)
    r = np.random.default_rng(8)
    letters = [chr(c) for c in range(0x20, 0x250)] + list(".,'’-–…!?€東\u0301\u200d")
    texts = [f"{a}b {b}{a}, x{a}." for a, b in zip(letters, letters[1:] + letters[:1])]
    texts += ["".join(r.choice([*letters, " ", " ", "."], 40)) for _ in range(1500)]
    assert [np.frombuffer(x, "<u4").tolist() for x in mine(texts)] == [tok.encode(t, add_special_tokens=False).ids for t in texts]


def test_words_are_split_and_remembered_as_bytes(monkeypatch):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    tok, mine = Tokenizer.from_file(path), token_output.word_tokenizer(path)
    texts = ["one\ttwo\nthree\x0bfour\x0cfive\rsix  seven ", "a\u00a0b\x1cc\x85d e\u2003f", "", "na\u00efve, 東京 two"]
    want = [tok.encode(t, add_special_tokens=False).ids for t in texts]
    monkeypatch.setattr(token_output, "REMEMBERED", 3)  # memory starts anew between texts
    assert [np.frombuffer(x, "<u4").tolist() for x in mine([t.encode() for t in texts])] == want
    assert mine([None, *texts]) == [b"", *mine([t.encode() for t in texts])]


def test_batches_of_long_texts_are_bounded_and_kept_text_travels_once(spark):
    from pyspark.sql import functions as F
    from pyspark.sql import types as T

    docs = spark.range(64, numPartitions=1).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 8 != 3, F.repeat(F.lit("é"), 300_000)).alias("text"))
    for keep in (["doc_id", "text"], ["doc_id"]):
        made = common.map_text(docs, keep, [("n", T.LongType())], lambda texts: [[sum(len(t or "") for t in texts)] * len(texts)])
        got = made.select("doc_id", "n", *[F.length(c).alias("chars") for c in keep[1:]]).collect()
        assert sorted(r.doc_id for r in got) == list(range(64))
        assert max(r.n for r in got) <= 4_000_000 // 2 + 300_000 + 300_000  # a batch of 4 MB and the row that fills it
        assert all(r.chars == (None if r.doc_id % 8 == 3 else 300_000) for r in got if len(keep) > 1)


def test_neighbours(spark, monkeypatch):
    monkeypatch.setattr(nn_descent, "BLOCK", 200)
    r = np.random.default_rng(0)
    x = r.normal(size=(700, 12))
    x[650:] = x[0]  # copies
    rows = [(i, v.tolist(), "n") for i, v in enumerate(x)] + [(3, x[3].tolist(), "again")] + [(1000, None, "n"), (1020, [0.0] * 12, "n"), (1040, [1.0] * 3, "n"), (1060, [float("nan")] * 12, "n"), (1080, [None] * 12, "n"), (None, x[1].tolist(), "n")]
    got = {}
    for q in nn_descent.neighbours(spark.createDataFrame(rows, "vec_id long, embedding array<double>, node string")).collect():
        got.setdefault(q.query_id, {})[q["rank"]] = (q.vec_id, q.score)
    hit = n = 0
    for i in range(0, 700, 20):
        s = x @ x[i]
        order = [j for j in np.lexsort((np.arange(700), -s)) if j != i][:20]
        assert sorted(got[i]) == list(range(1, 21)) and all(np.isclose(s[v], t) for v, t in got[i].values())
        hit, n = hit + len({v for v, _ in got[i].values()} & set(order)), n + 20
    assert hit / n > 0.95 and set(got) == set(range(0, 700, 20))
    assert nn_descent.neighbours(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0
    few = spark.createDataFrame([(i, [float(i), 1.0]) for i in range(5)], "vec_id long, embedding array<double>")
    assert [r.vec_id for r in nn_descent.neighbours(few).orderBy("rank").collect()] == [1, 2, 3, 4]


def test_descent_and_search_cut_nothing(spark, monkeypatch):
    r = np.random.default_rng(4)
    # Leaves that know only their centre: after one round each knows all the others.
    x = r.normal(size=(17, 8)).astype(np.float16)
    leaves = list(range(1, 17))
    nodes = spark.createDataFrame([(0, i, v.tobytes(), v.astype(float).tobytes()) for i, v in enumerate(x)], "block int, node long, short binary, exact binary")
    f = lambda a, b: float(x[a].astype(np.float32) @ x[b].astype(np.float32))
    low = float("-inf")
    graph = [(0, 0, leaves, [f(0, i) for i in leaves], [False] * 16, leaves, [], low, 16)] + [(0, i, [0], [f(i, 0)], [False], [0], [], low, 1) for i in leaves]
    graph = spark.createDataFrame(graph, nn_descent._GRAPH)
    assert all(set(g.near) == set(range(17)) - {g.node} for g in nn_descent.descend(nodes, graph, 17, 1).collect())
    # An edge stays new until it has been handed on; what was handed on counts as old.
    known = spark.createDataFrame([(0, 0, list(range(1, 21)), [1.0 - i / 100 for i in range(20)], [True] * 20)], "block int, node long, near array<long>, score array<float>, fresh array<boolean>")
    found = spark.createDataFrame([], nn_descent._PROPOSED)
    g = nn_descent.joined_back(known, found, 1).first()
    assert g.new == list(range(1, 17)) and g.old == [] and g.fresh == [False] * 16 + [True] * 4 and g.changed == 0
    # A chain of nodes, each known to the one before it only.
    n = 12
    chain = spark.createDataFrame([(0, i, b"", np.array([float(i + 1), 1.0]).tobytes()) for i in range(n)], "block int, node long, short binary, exact binary")
    adjacency = spark.createDataFrame([(i, [i + 1]) for i in range(n - 1)], "node long, adjacent array<long>")
    query = spark.createDataFrame([(0, np.array([1.0, 0.0]).tobytes(), [0])], "q long, vector binary, start array<long>")
    assert [h.node for h in nn_descent.search(chain, adjacency, query, 1, 1, 256).collect()] == [n - 1]
    # Rounds go on until edges have settled.
    calls = []
    from pyspark.sql import functions as F

    monkeypatch.setattr(nn_descent, "start_graph", lambda *_: graph)
    monkeypatch.setattr(nn_descent, "descend", lambda nodes, graph, count, turn: calls.append(1) or graph.withColumn("changed", F.lit(100 if len(calls) < 9 else 0)))
    nn_descent.build(nodes, 17)
    assert len(calls) == 9


def test_every_size_is_worked_on_alike():
    for n in (500, 2000, 10_000, 50_000, 3_000_000):
        deals, cells = nn_descent.deals_for(n)
        assert cells > 1 and n / cells <= nn_descent.LEAF and deals * cells <= nn_descent.MOST_SEEDS
    deals, cells = nn_descent.deals_for(10**10)
    assert deals * cells <= nn_descent.MOST_SEEDS


CLASHING = ["_text", "_words", "_lines", "t_lang", "o_total", "Kept", "N_WORDS", "n_lines", "row", "_fp", "_node", "root", "turn", "_turn", "node", "fp", "word", "part", "path", "ids", "h", "size", "key", "range", "taken", "g_source", "s_node", "f_id", "hit", "p_url", "x", "_label", "_id"]


def test_columns_of_any_name_come_through(spark, table):
    """Extra columns with names that operators use inside keep their values; those named like a result are replaced."""
    names = ["doc_id", "text", "lang", "source", *CLASHING]
    docs = spark.createDataFrame([(i, t, lang, s, *[f"{c} {i}" for c in CLASHING]) for i, t, lang, s, *_ in corpus(30)[:30]], "doc_id long, text string, lang string, source string, " + ", ".join(f"`{c}` string" for c in CLASHING))

    def whole(df, gone=()):
        kept = [c for c in CLASHING if c.lower() not in gone]
        rows = df.collect()
        assert rows and all(r[c] == f"{c} {r.doc_id}" for r in rows for c in kept)

    from catalog_dedup.llm import near_copies

    whole(quality_rules.apply_rules(docs, names), ("kept", "n_words"))
    whole(simhash.one_of_each(docs))
    whole(near_copies.one_of_each(docs))
    whole(mixing.mix(docs))
    whole(language_id.identify(docs, names))
    whole(quality_classifier.score(docs, quality_classifier.fit(docs, spark.createDataFrame([(i, i % 2) for i in range(30)], "doc_id long, quality int")), names))
    whole(token_counts.count_tokens(docs, table, names))
    whole(lattice.encode(docs, table, names), ("ids",))
    rules = spark.createDataFrame([("com", "/", "allow")], "host string, path string, verdict string")
    pages = docs.withColumnRenamed("text", "url")
    whole(url_filters.judge(pages, rules, [c for c in pages.columns if c != "url"]), ("path",))
    assert simhash.duplicate_classes(docs).count() == 30 and mixing.mix_sizes(docs).count() == 30
    assert token_output.read_shards(token_output.write_shards(docs, public_tokenizers.path("word_bpe_49k.json"))).count() == 30


def test_units_of_any_length(spark, table, monkeypatch):
    """Long units go block by block, and long pre-tokens without a trie; both as brute force has it."""
    texts = ["ab" * 3000 + "東" * 300 + "é" * 700, "x" * 5000, "a" * 65, "e" * 64, "short"]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    split = pieces.splitter(table)
    want = [[i for w in split(t) for i in best_path(w, table)] for t in texts]
    for head in (lattice.HEAD, 1):
        monkeypatch.setattr(lattice, "HEAD", head)
        got = {r.doc_id: r for r in lattice.encode(rows, table, ["doc_id"]).collect()}
        assert [list(got[i].ids) for i in range(len(texts))] == want and all(r.round_trip for r in got.values())
    counts = {r.doc_id: r.n_tokens for r in token_counts.count_tokens(rows, table, ["doc_id"]).collect()}
    assert [counts[i] for i in range(len(texts))] == list(map(len, want))


def test_units_cut_alike_whatever_the_slice(table, monkeypatch):
    from catalog_dedup.llm import units

    cutter = units.Cutter(table)
    texts = ["the end  of   it\nand so on. " * 30, None, "", "東京 ñ", "aaaa" * 50]

    def cut():
        out = [[] for _ in texts]
        for codes, heads, owner in cutter.blocks(texts):
            s = codes.tobytes().decode("utf-32-le")
            for k, a, b in zip(owner.tolist(), heads[:-1].tolist(), heads[1:].tolist()):
                out[k].append(s[a:b])
        return out

    plain = cut()
    assert ["".join(x) for x in plain] == [("▁" + t).replace(" ", "▁") if t else "" for t in texts]
    monkeypatch.setattr(units, "SLICE", 16)
    assert cut() == plain
    every = sorted({u for x in plain for u in x})
    assert len(set(zip(*[h.tolist() for h in units.hashes_of(every)]))) == len(every)


def test_statistics_equal_plain_counts():
    for text in ["", "Hello, World! It is 42 | 7 #tag\nline two\nline two", " a  a b B b b ", "ÄÖ ñ 東京 … x|y", "w " * 3000]:
        got = dict(zip(quality_classifier.FEATURES, quality_classifier.statistics(text)))
        w = text.split()
        n, lines = max(len(w), 1), [x for x in text.split("\n") if x.strip()]
        count = lambda f: sum(map(f, text))
        want = {
            "words": len(w), "word_length": sum(map(len, w)) / n, "distinct_words": len(set(w)) / n, "distinct_pairs": len({(w[i], w[i + 1]) for i in range(len(w) - 1)}) / n,
            "stutters": sum(w[i] == w[i + 1] for i in range(len(w) - 1)) / n, "lines": len(lines) / n, "distinct_lines": len(set(lines)) / max(len(lines), 1),
            "digits": count(lambda c: c in "0123456789") / max(len(text), 1), "symbols": count(lambda c: c in "#*$%&<>@^~=+_") / n, "exclamations": count(lambda c: c in "!?") / n,
            "stops": count(lambda c: c in ".,") / n, "bars": text.count("|") / n, "longest_word": max(map(len, w), default=0), "title_words": sum(x.istitle() for x in w) / n,
        }
        assert all(np.isclose(got[k], v) for k, v in want.items())


def test_language_equals_one_text_at_a_time(spark):
    """Predictions against trigrams counted one by one and machines asked one by one."""
    words = {"en": "the heon onhe of and with", "de": "und der schei über nicht ein", "fr": "les éau leçon de la pour", "ru": "это что как был они при"}
    rows = [(i, " ".join(np.random.default_rng(i).permutation(words[k].split() * 4)), k) for i in range(120) for k in [sorted(words)[i % 4]]]
    rows += [(3, rows[3][1], "ru"), (200, None, "en"), (201, "", "en"), (202, "7 !", "en"), (203, "über THE 東京 " * 4000, None), (None, "les de la", "fr")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.fit(docs, remainder_is_not(language_id.FOLDS, language_id.HELD_OUT))

    def counts(text):
        letter = lambda c: "a" <= c <= "z" or (ord(c) >= 0xC0 and c not in "×÷" and not 0x2000 <= ord(c) <= 0x2BFF)
        s = ""
        for c in text.lower():
            c = c if letter(c) else " "
            s += "" if c == " " and s.endswith(" ") else c
        out, s = np.zeros(language_id.DIM), f" {s} "
        for a, b, c in zip(s, s[1:], s[2:]):
            h = (ord(a) * 0x9E3779B1 + ord(b) * 0x85EBCA77 + ord(c) * 0xC2B2AE3D) * 0x27D4EB2F165667C5 % 2**64
            out[(h >> 52) % language_id.DIM] += 1
        return out

    def vote(m, x):
        k = len(m["names"])
        won = np.ones((k, k))
        for (a, b), w in zip(m["pairs"], m["w"]):
            won[a, b] = 1 / (1 + np.exp(-3 * (float(w[:-1] @ x) + float(w[-1]))))
            won[b, a] = 1 - won[a, b]
        best = int(np.argmax(won.sum(1)))
        return m["names"][best], min([won[best, j] for j in range(k) if j != best], default=1.0)

    got = sorted(((r.doc_id, r.lang_pred, round(r.score, 4)) for r in language_id.predict(docs, model, ["doc_id"]).collect()), key=str)
    want = []
    for i, t, _ in rows:
        if not t or not any(map(str.isalpha, t)):
            want.append((i, "und", 0.0))
            continue
        x = np.sqrt(counts(t)).astype(np.float32)
        x /= np.sqrt(x @ x)
        family, p = vote(model["family"], x)
        lang, q = vote(model["within"][family], x)
        want.append((i, lang, round(p * q, 4)))
    assert [g[:2] for g in got] == [w[:2] for w in sorted(want, key=str)]
    assert all(abs(g[2] - w[2]) < 2e-3 for g, w in zip(got, sorted(want, key=str)))


def remainder_is_not(parts, k):
    from pyspark.sql import functions as F

    from catalog_dedup.llm.common import remainder

    return remainder(F.col("doc_id"), parts) != k


def test_listed_urls(spark):
    rules = spark.createDataFrame([("com", "/", "allow")], "host string, path string, verdict string")
    listed = spark.createDataFrame([("http://Bad.example.org:80",), ("https://x.org/a%7eb?q=1#top",), ("http://other.com/",), ("nothing",), (None,)], "url string")
    urls = ["https://bad.example.org/any/page", "http://www.bad.example.org", "http://notbad.example.org/", "http://x.org:80/a~b?q=1", "http://x.org/a~b", "http://other.com/", "http://bad.example.org.:443/p", "http://" + "a." * 5000 + "org/", None, ""]
    got = {r.page_id: (r.rule, r.verdict) for r in url_filters.judge(spark.createDataFrame(list(enumerate(urls)), "page_id int, url string"), rules, ["page_id"], listed=listed).collect()}
    assert [got[i] for i in range(len(urls))] == [(None, "block"), (None, "block"), (None, "allow"), (None, "block"), (None, "allow"), ("com/", "allow"), (None, "block"), (None, "allow"), (None, "allow"), (None, "allow")]
    assert url_filters.judge(spark.createDataFrame([], "page_id int, url string"), rules, ["page_id"], listed=listed).count() == 0
    # Few blocks are crowded and pass more, but never lose a key.
    h = np.arange(5000, dtype=np.int64) * 104729
    keys = spark.createDataFrame([(int(x),) for x in h], "h long")
    assert (url_filters.built(keys, 5000) == url_filters.blocked_bloom(h)).all() and url_filters.possible(url_filters.blocked_bloom(h, 2), h).all()
