import random

import brute
import numpy as np
import pyarrow as pa
import pytest

from suffix_engine.llm import blocks, lines, segments, substring, windows

CASES = [(lines.line_digests, brute.lines), (substring.substring_digests, brute.substrings), (windows.window_digests, brute.windows)]


def result(df):
    return {r[0]: tuple(r[1:]) for r in df.collect()}


@pytest.mark.parametrize("seed", [1, 2, 3])
@pytest.mark.parametrize("operator,expected", CASES)
def test_equals_brute_force(spark, operator, expected, seed):
    rows = brute.sample_texts(seed)
    docs = spark.createDataFrame([(d, t, "x", 1, b"p") for d, t in rows], "doc_id long, text string, block string, bucket int, payload binary")
    assert result(operator(docs)) == expected(rows)


@pytest.mark.parametrize("operator,expected", CASES)
def test_given_documents(spark, operator, expected):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    assert result(operator(docs)) == expected(rows)


@pytest.mark.parametrize("operator,_", CASES)
def test_edges(spark, operator, _):
    schema = "doc_id long, text string"
    assert operator(spark.createDataFrame([], schema)).collect() == []
    rows = [(None, "word " * 30), (7, "word " * 30), (7, "word " * 30), (None, None), (8, "é" * 70000 + " z" * 70000)]
    assert operator(spark.createDataFrame(rows, schema)).count() == 5


@pytest.mark.parametrize("operator,kernel,expected", [(lines.line_digests, lines, brute.lines), (substring.substring_digests, segments, brute.substrings), (windows.window_digests, segments, brute.windows)])
def test_two_passes_give_the_same(spark, monkeypatch, operator, kernel, expected):
    """With a few bundles to a block the items go through relays."""
    rows = brute.sample_texts(4)
    monkeypatch.setattr(kernel, "exchange", lambda *a, **k: blocks.exchange(*a, **k, fan=3))
    assert result(operator(spark.createDataFrame(rows, "doc_id long, text string"))) == expected(rows)


@pytest.mark.parametrize("n_buckets", [8, 80, 800, 80_000])
def test_bundles_of_a_block_are_bounded(n_buckets):
    table = pa.table({"doc_id": pa.array([d for d, _ in brute.sample_texts(5)], pa.int64()), "text": pa.array([t for _, t in brute.sample_texts(5)], pa.string())})
    items, _ = substring.SubstringKernel().items(blocks.Docs(table), n_buckets)
    fan = 16
    ranges = np.unique(items.bucket * min(fan, n_buckets) // n_buckets)
    assert (np.diff(items.bucket) >= 0).all() and items.bucket.max() < n_buckets and len(ranges) <= fan
    again, _ = blocks.Items.joined([items.between(0, 5).packed(), items.between(5, len(items)).packed()])
    assert np.array_equal(again.data, items.data) and all(np.array_equal(a, b) for a, b in zip(again.columns, items.columns, strict=True))


def test_structured_texts_have_hashes_of_their_own():
    texts = [x.encode() for n in (8, 16, 64, 256, 1024, 4096) for x in brute.thue_morse(n)] + [b"a" * n for n in range(1, 600)] + [b"\0" * n for n in range(1, 300)]
    data = np.frombuffer(b"".join(texts), np.uint8)
    end = np.cumsum([len(x) for x in texts])
    begin = end - [len(x) for x in texts]
    assert len(np.unique(blocks.range_hashes(data, begin, end))) == len(set(texts))


def test_a_common_gram_draws_no_bucket(spark):
    """One gram in a third of all windows: it is set aside, and the pieces spread over the buckets."""
    r = random.Random(9)
    key_of = lambda g: int(blocks.mix(blocks.mix(blocks.words_at(g)[:1]) + blocks.words_at(g)[8:9])[0])
    common = min((f"zqzq gram no{i:04d}" for i in range(2000)), key=lambda x: key_of(np.frombuffer(x.encode(), np.uint8)))
    letters = lambda n: "".join(r.choice("abcdefgh ") for _ in range(n))
    rows = [(i, letters(40) + common + letters(60) + common + letters(200)) for i in range(3000)]
    table = pa.table({"doc_id": pa.array([d for d, _ in rows], pa.int64()), "text": pa.array([t for _, t in rows], pa.string())})
    kernel = substring.SubstringKernel()

    def heaviest():
        items, _ = kernel.items(blocks.Docs(table), 16)
        bytes_of = np.bincount(items.bucket, weights=items.size, minlength=16)
        return bytes_of.max() / bytes_of.mean()

    before = heaviest()
    kernel.avoid = segments.hot_minimisers(spark.createDataFrame(rows, "doc_id long, text string"), kernel, 60_000, 1)
    assert key_of(np.frombuffer(common.encode(), np.uint8)) in kernel.avoid.tolist()
    assert before > 4 and heaviest() < 1.5


def test_pieces_are_found_with_minimisers_set_aside(spark):
    rows = brute.sample_texts(6)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for kernel, expected, columns in [(substring.SubstringKernel(), brute.substrings, 2), (windows.WindowKernel(), brute.windows, 2)]:
        out = segments.exchange_runs(docs, kernel, hot_bytes=2000, one_of=1)
        assert len(kernel.avoid)
        want = {d: w[:2] for d, w in expected(rows).items()}
        if isinstance(kernel, windows.WindowKernel):
            assert {r.doc_id: (r.n_words, r.n_removed) for r in out.collect()} == want
        else:
            assert {r.doc_id: (r.n_bytes, sum(s.end - s.begin for s in r.spans)) for r in out.collect()} == want


def test_lines_that_clash_in_half_of_their_digest_are_kept_apart():
    key, print_ = np.array([5, 5, 5, 9, 5], np.uint64), np.array([1, 2, 1, 7, 3], np.uint64)
    index = lines.LineIndex.build(key, print_, np.array([2, 4, 1, 3, 1]), np.array([10, 20, 30, 40, 50]), 3)
    assert index.last_holder(key, print_).tolist() == [30, 20, 30, 40, lines.NOT_THERE]
    assert index.last_holder(np.array([6], np.uint64), np.array([1], np.uint64)).tolist() == [lines.NOT_THERE]


def test_run_length_index_gives_the_match_a_row_above():
    r = np.random.default_rng(2)
    pieces = [r.integers(97, 99, n).astype(np.uint8) for n in (30, 1, 50, 50, 7)] + [np.full(40, 97, np.uint8)] * 2
    begin = np.r_[0, np.cumsum([len(p) for p in pieces])]
    text = np.concatenate(pieces)
    index = substring.RunLengthIndex.build(text, begin)
    assert int(index.lengths.sum()) == len(text) and len(index.heads) < len(text)
    ends = np.repeat(begin[1:], np.diff(begin))
    suffixes = sorted((text[i : ends[i]].tobytes(), int(ends[i]), i) for i in range(len(text)))
    place, length = index.matching()
    common = lambda a, b: next((k for k, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
    for (a, _, i), (b, _, j) in zip(suffixes, suffixes[1:], strict=False):
        assert length[j] == common(a, b) and (length[j] == 0 or place[j] == i)
