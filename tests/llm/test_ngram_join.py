import random

import brute
import numpy as np
import pytest

from suffix_engine.llm import graph, ngram_join


def result(df):
    return {r.doc_id: (r.n_shingles, r.component_id) for r in df.collect()}


@pytest.mark.parametrize("seed,size,percent,group", [(1, 4, 85, 2048), (2, 4, 85, 3), (3, 2, 40, 4), (4, 5, 80, 2048), (5, 2, 60, 2)])
def test_equals_brute_force(spark, seed, size, percent, group):
    rows = brute.sample_texts(seed, 90)
    docs = spark.createDataFrame([(d, t, 1, 2) for d, t in rows], "doc_id long, text string, rep int, hub int")
    assert result(ngram_join.components(docs, size, percent, group=group)) == brute.jaccard_components(rows, size, percent)


def test_given_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    assert result(ngram_join.components(docs)) == brute.jaccard_components(rows)


def test_edges(spark):
    schema = "doc_id long, text string"
    assert ngram_join.components(spark.createDataFrame([], schema)).collect() == []
    rows = [(5, "a b c d e"), (None, "A b  c d\te"), (3, "a b c d e"), (3, "a b c d e"), (9, None), (8, " "), (7, "x"), (6, "X")]
    got = sorted((r.doc_id or -1, r.component_id) for r in ngram_join.components(spark.createDataFrame(rows, schema)).collect())
    assert got == [(-1, 3), (3, 3), (3, 3), (5, 3), (6, 6), (7, 6), (8, 8), (9, 9)]


def test_search_equals_intersection():
    r = np.random.default_rng(0)
    for _ in range(20):
        sets = [np.unique(r.integers(0, 60, r.integers(5, 40))) for _ in range(40)]
        index = ngram_join.Lists(sets)
        for q in range(40):
            need = int(r.integers(1, len(sets[q]) + 1))
            got = dict(index.search(q, need, 0, q, lambda found: np.zeros(len(found), bool)))
            want = {i: len(np.intersect1d(sets[i], sets[q])) for i in range(q)}
            assert got == {i: n for i, n in want.items() if n >= need}


def test_connected_components(spark):
    r = random.Random(3)
    edges = [(i, i + 1) for i in range(40)] + [(100 + r.randrange(60), 100 + r.randrange(60)) for _ in range(40)] + [(7, 7), (500, 200)]
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    want = {x: find(x) for e in edges for x in e if e[0] != e[1]}
    assert dict(map(tuple, graph.connected(spark.createDataFrame(edges, "u long, v long")).collect())) == want


def test_template_texts_meet_in_lists_and_not_in_whole_groups(spark, monkeypatch):
    """Texts of few sentences hang together by common shingles and hardly link: what a set is held against follows its lists."""
    r = random.Random(1)
    sentences = [" ".join("".join(r.choice("abcdefgh") for _ in range(5)) for _ in range(8)) for _ in range(20)]
    rows = [(i, " ".join(r.sample(sentences, 6))) for i in range(300)]
    rows += [(1000 + i, rows[i][1] + " end") for i in range(0, 300, 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert result(ngram_join.components(docs, group=16)) == brute.jaccard_components(rows)


def test_hub_first_finds_the_same_components():
    r = np.random.default_rng(5)
    for _ in range(20):
        base = [np.unique(r.integers(0, 400, 40)) for _ in range(3)]
        sets = sorted((np.unique(np.r_[r.permutation(base[r.integers(0, 3)])[: r.integers(34, 41)], r.integers(400, 500, r.integers(0, 4))]) for _ in range(30)), key=len)
        size = np.array([len(x) for x in sets])
        part = ngram_join.linked(sets, size, int(r.integers(0, 30)), 80)
        root = list(range(30))
        for i in range(30):
            for j in range(i):
                both = len(np.intersect1d(sets[i], sets[j]))
                if 100 * both >= 80 * (size[i] + size[j] - both):
                    a, b = root[i], root[j]
                    root = [b if x == a else x for x in root]
        assert len({(int(p), q) for p, q in zip(part, root, strict=True)}) == len(set(part.tolist())) == len(set(root))


def test_long_texts_and_ties(spark):
    long = " ".join(f"w{i % 4999}" for i in range(100_000))
    rows = [(2, long), (9, long + " end"), (5, "z " + long), (7, "x " * 50_000), (8, "x " * 3)]
    got = result(ngram_join.components(spark.createDataFrame([(*r, "k") for r in rows], "doc_id long, text string, component_id string")))
    assert got == brute.jaccard_components(rows)


def test_sets_out_of_reach_are_not_searched(monkeypatch):
    """Copies that share with others too little of their sets for a link with sets of their size."""
    searched, search = [], ngram_join.Lists.search
    monkeypatch.setattr(ngram_join.Lists, "search", lambda self, query, *rest: searched.append(query) or search(self, query, *rest))
    r = np.random.default_rng(2)
    far = [np.sort(r.permutation(400)[:360]) for _ in range(12)]
    part = ngram_join.linked_with_probes(far + far[:4], np.full(16, 400), 12, 85)
    assert not searched and len(set(part.tolist())) == 16
    near = [np.sort(r.permutation(400)[:398]) for _ in range(3)]
    part = ngram_join.linked_with_probes(far + near + near[:1], np.full(16, 400), 15, 85)
    assert searched == [15] and part[12] == part[13] == part[14] == part[15] and len(set(part.tolist())) == 13


def test_far_copies_of_one_text(spark):
    """Copies with many changes each, in a group that is cut: the least id is not the text that they are copies of."""
    r = random.Random(6)
    base = ["".join(r.choice("abcdefgh") for _ in range(6)) for _ in range(200)]
    rows = []
    for i in range(120):
        words = list(base)
        for at in r.sample(range(200), r.randrange(1, 12)):
            words[at] = f"x{i}y{at if r.random() < 0.5 else 0}"
        rows.append((i, " ".join(words[: r.choice((200, 200, 190, 170))])))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert result(ngram_join.components(docs, group=8)) == brute.jaccard_components(rows)
