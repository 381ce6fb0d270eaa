"""Near copies by five-word shingles against all pairs."""

import numpy as np
import pytest

pytest.importorskip("catalog_dedup.llm.near_copies")

from catalog_dedup.llm import near_copies  # noqa: E402


def shingles(text):
    w = (text or "").lower().split()
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def roots_of(rows):
    """Smallest doc_id of each row's group, by all pairs."""
    sets = [shingles(t) for _, t, *_ in rows]
    root = list(range(len(rows)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both >= 0.8 * (len(sets[i]) + len(sets[j]) - both) and top(i) != top(j):
                a, b = sorted((top(i), top(j)), key=lambda k: rows[k][0])
                root[b] = a
    return [rows[top(i)][0] for i in range(len(rows))]


@pytest.fixture(scope="module")
def rows():
    r = np.random.default_rng(5)
    words = [f"w{k}" for k in range(3000)]
    out = []
    for base in range(60):
        w = [words[k] for k in r.integers(0, 3000, 100 + base)]
        out.append((base * 20, " ".join(w)))
        for copy in range(1, 6):
            v = list(w)
            for at in r.choice(len(v), copy, replace=False):  # one to five changed words
                v[at] = words[r.integers(0, 3000)]
            out.append((base * 20 + copy, " ".join(v)))
    out += [(5000, None), (5001, ""), (5002, "one two"), (5003, "ONE\ttwo"), (5004, "one two three"), (5005, "x " * 30_000), (5006, "x y " * 9000)]
    return out


def test_groups_equal_brute_force(spark, rows):
    docs = spark.createDataFrame([(i, t, 1, "k") for i, t in rows], "doc_id long, text string, s_node int, root string").repartition(3)
    got = near_copies.one_of_each(docs).collect()
    want = sorted(set(roots_of(rows)))
    assert sorted(r.doc_id for r in got) == want and all(r.s_node == 1 and r.root == "k" for r in got)


def test_repeats_nulls_and_empty_tables(spark, rows):
    some = rows[:12] + rows[:12] + [(None, rows[0][1]), (None, "quite another text of some words")]
    docs = spark.createDataFrame(some, "doc_id long, text string")
    got = [r.doc_id for r in near_copies.one_of_each(docs).collect()]
    assert sorted(got, key=str) == sorted([*sorted(set(roots_of(rows[:12]))), None], key=str)
    assert near_copies.one_of_each(docs.limit(0)).count() == 0


def test_large_group_makes_few_verifications(spark, monkeypatch):
    r = np.random.default_rng(6)
    base = [f"w{k}" for k in r.integers(0, 3000, 300)]
    rows = []
    for i in range(600):
        v = list(base)
        v[r.integers(0, 300)] = f"new{i}"
        rows.append((i, " ".join(v)))
    seen = []
    checked = near_copies.verified
    monkeypatch.setattr(near_copies, "verified", lambda pairs, *a: seen.append(pairs.count()) or checked(pairs, *a))
    assert [x.doc_id for x in near_copies.one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()] == [0]
    assert sum(seen) < 6 * len(rows)


@pytest.mark.parametrize("most", [64, 0])
def test_no_link_is_lost_when_tables_find_none(spark, rows, monkeypatch, most):
    none = lambda *_: spark.createDataFrame([], "a long, b long, d int")
    monkeypatch.setattr(near_copies, "candidates", none)
    monkeypatch.setattr(near_copies, "PAIRS", most, raising=False)
    common = " ".join(f"line{k}" for k in range(40))  # in many texts, which stay apart
    texts = [(i, t) if i % 3 or t is None else (i, f"{t} {common}") for i, t in rows]
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    assert sorted(r.doc_id for r in near_copies.one_of_each(docs).collect()) == sorted(set(roots_of(texts)))


def test_parities_are_bounds():
    r = np.random.default_rng(7)
    for size in (3, 300, 2040, 2100, 40_000):
        x = np.unique(r.integers(0, 2**63, size, dtype=np.uint64))
        y = np.unique(np.r_[x[size // 10 :], r.integers(0, 2**63, size // 12, dtype=np.uint64)])
        z = np.unique(r.integers(0, 2**63, size, dtype=np.uint64))
        for make in (near_copies.parities, near_copies.wide_parities):
            d = near_copies.differing([make(x), make(x), make(x)], [make(y), make(z), make(x)])
            assert d[0] <= len(np.setxor1d(x, y)) and d[2] == 0
        assert size < 300 or d[1] > 0.25 * size  # far sets are told apart


def filed_rows(spark, n, shared):
    """Nodes of one crowded shingle that have ``shared`` other shingles in common, and their parities."""
    r = np.random.default_rng(8)
    passage = r.integers(0, 2**63, shared, dtype=np.uint64)
    sets = [np.unique(np.r_[passage, r.integers(0, 2**63, 300, dtype=np.uint64)]) for _ in range(n - 2)]
    sets += [sets[0][3:], sets[-1][3:]]  # a near copy of the first and of the last
    nodes = [(k, near_copies.parities(s), near_copies.wide_parities(s)) for k, s in enumerate(sets)]
    filed = spark.createDataFrame([(7, k, k, len(s), 0) for k, s in enumerate(sets)], "key long, node long, root long, size int, at int")
    return filed, spark.createDataFrame(nodes, "s_node long, s_odd binary, s_wide binary")


@pytest.mark.parametrize("block", [512, 16])
def test_crowded_shingle_writes_rows_in_proportion(spark, monkeypatch, block):
    monkeypatch.setattr(near_copies, "BLOCK", block, raising=False)
    filed, nodes = filed_rows(spark, 100, 20)  # 4,950 pairs, of which two are near copies
    met = near_copies.meeting(filed, 0, 0.8, False)
    assert met.count() <= 100 * -(-100 // block)
    found = near_copies.compared(met.filter("cell IS NOT NULL"), nodes, 0, 0.8).collect()
    assert {(0, 98), (97, 99)} <= {(x.a, x.b) for x in found} and len(found) < 20


def test_links_join_alike_in_one_task_and_in_rounds(spark, monkeypatch):
    r = np.random.default_rng(9)
    edges = [(int(a), int(b)) for a, b in r.integers(-300, 300, (250, 2))] + [(k, k + 1) for k in range(1000, 1200)]
    links = spark.createDataFrame(edges, "a long, b long")
    one = {(x.node, x.root) for x in near_copies.joined(links).collect()}
    monkeypatch.setattr(near_copies.shared, "BROADCAST_ROWS", 10)
    rounds = {(x.node, x.root) for x in near_copies.joined(links).collect()}
    assert one == rounds and (1200, 1000) in one
