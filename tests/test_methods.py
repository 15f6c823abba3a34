"""Distributed methods against the definitions."""

import gc
import random
import time
from pathlib import Path

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from suffix_engine import queries, session
from suffix_engine.operators import bucketed, bwt, compress, corpus, doubling, features, fm, hybrid, kmers, lcp, metrics, naive, partial, suffix_array, verify
from suffix_engine.session import cut, cut_by
from test_kernels import GOLDEN

TEXT = "the cat and the hat sat on the mat; the cat sat. " * 6 + "zzzzzzzzzzzzzzzzzzzz é$ tail"


def sa_of(text, order="smallest"):
    end = "" if order == "smallest" else "\U0010ffff"
    return sorted(range(len(text) + 1), key=lambda i: text[i:] + end)


def ranks(df):
    return [r.pos for r in df.orderBy("rnk").collect()]


def positions(df):
    rows = df.orderBy("rank").collect()
    assert [r["rank"] for r in rows] == list(range(len(rows)))
    return [r["pos"] for r in rows]


@pytest.fixture(scope="module")
def small(spark):
    return corpus.literal(spark, TEXT)


@pytest.fixture(scope="module")
def small_sa(small):
    return bucketed.build(small).cache()


def test_assembly(spark):
    rows = spark.createDataFrame([(3, "b$"), (1, "aé"), (2, None), (4, ""), (9, "z")], "k long, t string")
    c = corpus.assemble(rows, "k", "t")
    codes = corpus.codes_on_driver(c)
    assert "".join(c.symbols[x] for x in codes) == "aé\nb$\n\nz$" and codes[-1] == 0 == c.terminator and c.n == 9
    assert c.counts.sum() == c.n and c.smaller.tolist() == np.r_[0, np.cumsum(np.bincount(codes))[:-1]].tolist()
    found = corpus.locate_documents(spark.createDataFrame([(0,), (4,), (7,)], "pos long"), c)
    assert sorted((r.pos, r.key, r.offset) for r in found.collect()) == [(0, 1, 0), (4, 3, 1), (7, 9, 0)]
    assert corpus.codes_on_driver(corpus.prefix_of(c, 4)).tolist() == [*codes[:4].tolist(), 0]
    empty = corpus.assemble(rows.limit(0), "k", "t")
    assert empty.n == 1 and corpus.text(empty).collect()[0].code == 0


def test_chunks_cover_the_text(small):
    codes = corpus.codes_on_driver(small)
    for r in corpus.chunks(small, 50, 7).collect():
        assert np.frombuffer(r.codes, "<u2").tolist() == codes[r.start : r.start + 57].tolist() and r.start == 50 * r.chunk


def test_kmers_and_their_index(small, spark):
    for k in (1, 3, 8):
        rows = kmers.readable(kmers.extract(small, k), small, k).collect()
        padded = TEXT + "$" * (k + 1)
        assert {(r.pos, r.word) for r in rows} == {(i, padded[i : i + k]) for i in range(small.n)}
    words = spark.createDataFrame([("cat",), ("zzz",), ("qqq",), ("t",)], "word string")
    assert {(r.word, r.pos) for r in kmers.lookup(small, 3, words).collect()} == {(w, i) for w in ("cat", "zzz") for i in range(len(TEXT)) if TEXT.startswith(w, i)}
    assert kmers.suggest_k(small, 4) >= 1


@pytest.mark.parametrize("text,order,sa,transform,primary", GOLDEN)
def test_golden(spark, text, order, sa, transform, primary):
    c = corpus.literal(spark, text, order)
    result = doubling.build(c, h0=1)
    assert ranks(result.ranks) == sa
    t = bwt.from_ranks(result.ranks, c)
    assert bwt.as_string(t, c) == transform and bwt.primary_index(result.ranks) == primary
    built = bucketed.build(c, k=3, r=4)
    assert positions(built) == sa
    assert [c.symbols[r.code] for r in built.orderBy("rank").collect()] == list(transform)


def test_rounds_of_the_worked_example(spark):
    """Largest terminator: after one round only the last A moves, after two all ranks are final. (A printed rank list of the example
    gives 1, 1 and 0 for the three suffixes that start with A; sorting the pairs gives 0, 0 and 2.)"""
    c = corpus.literal(spark, "BANANA", "largest")
    by_pos = lambda df: [r.rnk for r in df.orderBy("pos").collect()]
    first = doubling.init_ranks(c)
    assert by_pos(first) == [3, 0, 4, 0, 4, 0, 6]
    one = doubling.one_round(first, 1)
    assert by_pos(one) == [3, 0, 4, 0, 4, 2, 6]
    assert by_pos(doubling.one_round(one, 2)) == [3, 0, 4, 1, 5, 2, 6]
    assert [r.r2 for r in doubling.shift(first, 1).orderBy("pos").collect()] == [0, 4, 0, 4, 0, 6]
    c = corpus.literal(spark, "BANANA")
    assert by_pos(doubling.init_ranks(c)) == [4, 1, 5, 1, 5, 1, 0]
    assert by_pos(doubling.one_round(doubling.init_ranks(c), 1)) == [4, 2, 5, 2, 5, 1, 0]
    assert len(doubling.build(c, h0=1, rounds="paper").rounds) == 1 + 4 and len(doubling.build(c, h0=1).rounds) == 1 + 2


@pytest.mark.parametrize("pairing", ["join", "union_reduce", "block"])
@pytest.mark.parametrize("rerank", doubling.RERANKS)
def test_doubling_variants(small, pairing, rerank):
    active = {"active_only": True} if rerank == "group" else {"active_only": False}
    result = doubling.build(small, pairing=pairing, rerank=rerank, h0=4, **active)
    assert ranks(result.ranks) == sa_of(TEXT)
    assert result.rounds[-1].unresolved == 0


def test_block_shift_equals_join(spark):
    r = random.Random(2)
    df = spark.createDataFrame([(i, r.randrange(50), True) for i in range(100)], "pos long, rnk long, tied boolean")
    for h in (1, 7, 8, 16, 20, 99, 120):
        a = {tuple(x) for x in doubling.pair_by_block(df, h, 8).collect()}
        assert a == {tuple(x) for x in doubling.pair_by_join(df, df, h).collect()} == {tuple(x) for x in doubling.pair_by_union(df, h).collect()}


@pytest.mark.parametrize("kernel", partial.KERNELS)
@pytest.mark.parametrize("splitters,reader", [("sampled", "broadcast"), ("histogram", "broadcast"), ("orderby", "broadcast"), ("sampled", "chunk_join"), ("histogram", "chunk_join")])
def test_bucketed_variants(small, kernel, splitters, reader):
    assert positions(bucketed.build(small, k=3, r=5, kernel=kernel, splitters=splitters, reader=reader)) == sa_of(TEXT)


def test_other_constructions(small):
    want = sa_of(TEXT)
    assert positions(bucketed.build(small, k=2, r=3, kernel="merge", reduction="span_direct")) == want
    assert ranks(hybrid.build(small, k=2).ranks) == want
    assert ranks(hybrid.build(small, k=1, most=5).ranks) == want
    assert positions(naive.mapreduce_sort(small, 2, 5)) == want
    assert naive.local_suffix_array(small).tolist() == want


@pytest.mark.parametrize("order", ["smallest", "largest"])
def test_rows(spark, order):
    texts = [(1, "BANANA"), (2, ""), (3, None), (4, "aé\U0001f600aé"), (5, "abab" * 20)]
    rows = spark.createDataFrame(texts, "k long, t string")
    want = {k: bwt.encode(t, order) for k, t in texts if t is not None}
    for make in (bwt.per_row, bwt.per_row_relational, naive.rotations_bwt):
        assert {r.k: (r.bwt, r.primary) for r in make(rows, "k", "t", order).collect()} == want
    got = naive.suffix_array(rows, "k", "t", order).collect()
    for k, t in texts:
        if t is not None:
            assert [r.pos for r in sorted(got, key=lambda r: r["rank"]) if r.k == k] == sa_of(t, order)


def test_inverse(small, small_sa):
    t = small_sa.select("rank", "code")
    got = bwt.invert(t, small).orderBy("pos").collect()
    assert [r.code for r in got] == corpus.codes_on_driver(small).tolist()


def test_pattern_search(spark, small, small_sa):
    t, sa = small_sa.select("rank", "code"), small_sa.select("rank", "pos")
    index = fm.build(t, sa, small, block=16, sample=4)
    words = ["the", "cat", "zz", "hat sat", "qqq", "e", TEXT[5:90], "ca§"]
    patterns = spark.createDataFrame(list(enumerate(words)), "pattern_id long, pattern string")
    occurs = {i: [p for p in range(len(TEXT)) if TEXT.startswith(w, p)] for i, w in enumerate(words)}
    counts = fm.count(index, patterns)
    assert {r.pattern_id: r.cnt for r in counts.collect()} == {i: len(p) for i, p in occurs.items()}
    short = patterns.where("char_length(pattern) < 10")
    assert {tuple(r) for r in fm.count_joined(index, short).collect()} == {tuple(r) for r in fm.count(index, short).collect()}
    for found in (fm.locate(index, counts), suffix_array.locate(counts, sa)):
        assert sorted((r.pattern_id, r.pos) for r in found.collect()) == sorted((i, p) for i, ps in occurs.items() for p in ps)
    keyed = suffix_array.search(sa, small, patterns.where("pattern in ('the', 'cat', 'zz', 'e', 'qqq')"))
    assert {r.pattern_id: (r.lo, r.hi) for r in keyed.collect()} == {r.pattern_id: (r.lo, r.hi) for r in counts.collect() if r.cnt and r.pattern_id in (0, 1, 2, 5)}
    near = {(r.pattern_id, r.mismatches): r.cnt for r in fm.count_approx(index, patterns.where("pattern_id in (1, 2)"), 1).collect()}
    for i in (1, 2):
        w = words[i]
        for e in (0, 1):
            want = sum(sum(a != b for a, b in zip(TEXT[p : p + len(w)], w)) == e for p in range(len(TEXT) - len(w) + 1))
            assert near.get((i, e), 0) == want


def test_runs_codes_and_prefixes(spark, small, small_sa):
    t, sa = small_sa.select("rank", "code"), small_sa.select("rank", "pos")
    codes = [r.code for r in t.orderBy("rank").collect()]
    runs = compress.rle(t, small.n)
    got = runs.orderBy("run").collect()
    assert [c for r in got for c in [r.code] * r.len] == codes and all(a.code != b.code for a, b in zip(got, got[1:]))
    assert compress.run_report(t, small.n).first().runs == len(got)
    assert compress.unrle(runs).exceptAll(t).count() == 0
    m = compress.mtf(t, small.sigma, 64)
    assert [r.code for r in compress.mtf(m, small.sigma, 64, inverse=True).orderBy("rank").collect()] == codes
    p = np.unique(codes, return_counts=True)[1] / len(codes)
    assert abs(compress.entropy(t, "code").first().bits + (p * np.log2(p)).sum()) < 1e-9
    order = sa_of(TEXT)
    want = [0]
    for a, b in zip(order, order[1:]):
        n = 0
        while max(a, b) + n < len(TEXT) and TEXT[a + n] == TEXT[b + n]:
            n += 1
        want.append(n)
    table = lcp.build(sa, small)
    assert [r.lcp for r in table.orderBy("rank").collect()] == want
    levels, r, h = [], cut(doubling.init_ranks(small)), 1
    while h < small.n:
        levels.append((h, r.select("pos", "rnk")))
        r, h = cut(doubling.one_round(r, h)), 2 * h
    assert [x.lcp for x in lcp.by_levels(sa, levels).orderBy("rank").collect()] == want
    s = lcp.summary(table, small.n).first()
    assert s.longest_repeat == max(want) and int(s.distinct_substrings) == len({TEXT[i:j] for i in range(len(TEXT)) for j in range(i + 1, len(TEXT) + 1)})
    assert {(r.pos) for r in lcp.longest_repeats(table).collect()} == {order[i] for i, x in enumerate(want) if x == max(want)}


def test_checks_find_damage(small, small_sa):
    sa = small_sa.select("rank", "pos")
    assert tuple(verify.check_suffix_array(sa, small).first()) == (small.n, small.n, small.n, 0, 0)
    swapped = sa.withColumn("rank", F.when(F.col("rank") == 10, 11).when(F.col("rank") == 11, 10).otherwise(F.col("rank")))
    assert verify.check_suffix_array(swapped, small).first().violations > 0
    assert verify.same_symbols(small_sa.select("rank", "code"), small).count() == 0
    for splitters in bucketed.SPLITTERS:
        rows = verify.bucket_property(bucketed.partition(small, 2, 4, splitters)).collect()
        assert all(r.apart for r in rows) and sum(r.members for r in rows) == small.n


def test_measures(small):
    costs = metrics.block_costs(small, 2, 4).collect()
    assert sum(r.members for r in costs) == small.n and all(r.touched == r.members * (r.l_max + 1) for r in costs)
    assert metrics.balance(bucketed.partition(small, 2, 4)).first().ratio >= 1
    seconds, kept = metrics.timed(lambda: corpus.text(small), 60)
    assert kept and metrics.megabytes_per_second(small, seconds) > 0


def test_bigrams(spark):
    rows = spark.createDataFrame([(1, "BANANA"), (2, "BANANA"), (3, "CATTATTAGGA"), (4, "")], "k long, t string")
    b = features.bwt_bigrams(rows, "k", "t")
    assert {(r.first, r.second): r.cnt for r in b.where("k = 1").collect()} == {("A", "N"): 1, ("N", "N"): 1, ("N", "B"): 1, ("B", "$"): 1, ("$", "A"): 1, ("A", "A"): 1}
    d = {(r.a, r.b): r.distance for r in features.distance(b, "k", spark.createDataFrame([(1, 2), (1, 3)], "a long, b long")).collect()}
    assert d[1, 2] == 0 and 0 < d[1, 3] <= 1


def test_splits_have_no_common_order(spark):
    rows = spark.createDataFrame([(i, f"text {i}") for i in range(20)], "k long, t string")
    out = naive.split_index(rows, "k", "t", 3).collect()
    assert len(out) == 3 and all(bwt.decode(r.bwt, r.primary).count("text") >= 1 for r in out)


@pytest.mark.parametrize("name", ["dna_merge", "dna_part_radix", "dna_part_doubling_published"])
def test_variants_run_on_experiment_texts(spark, name):
    known = queries.queries()
    assert all(f"check_{text}_{v}" in known for text, own in queries.WHOLE.items() for v in [*own, "refine", "inverse"])
    assert all(f"check_dna_{v}" in known or f"check_dna_part_{v}" in known for v in queries._variants())
    row = known[f"check_{name}"](spark, "/root/testdata/sf0.001").first()
    assert row.n == row.rows == row.positions > 10_000 and row.misplaced == row.violations == 0


def test_published_doubling(small):
    """From one symbol, a fixed number of rounds; reach doubles and groups never fall."""
    result = queries._published(small)
    assert ranks(result.ranks) == sa_of(TEXT)
    assert len(result.rounds) == 2 + int(np.ceil(np.log2(small.n))) and [r.reach for r in result.rounds] == [1 << i for i in range(len(result.rounds))]
    groups = [r.groups for r in result.rounds]
    assert groups[0] == small.sigma and groups == sorted(groups) and groups[-1] == small.n
    assert [r.groups for r in hybrid.build(small, k=1).rounds] == groups[: len(hybrid.build(small, k=1).rounds)]


def test_ranks_stay_by_position(small):
    """In a round of the hybrid only unresolved ranks are exchanged, and those that lie by position aren't sorted again."""
    start = cut_by(doubling.init_ranks(small, 2), "pos")
    new = cut(doubling.rerank_in_groups(doubling.pair_by_join(start.where("tied"), start, 2)))
    again = cut_by(doubling.with_new(start, new))
    assert again.sparkSession.conf.get("spark.sql.adaptive.enabled") == "true"
    plan = doubling.pair_by_join(again.where("tied"), again, 4)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and plan.count("Sort [") == 1


def test_a_run_is_stopped_at_the_cut_off(spark):
    seconds, kept = metrics.timed(lambda: spark.range(10**13).selectExpr("sum(hash(id) % 7) as x"), 2)
    assert (seconds, kept) == (2, False)
    assert metrics.timed(lambda: spark.range(10), 60)[1]
    with pytest.raises(Exception, match="no_such"):
        metrics.timed(lambda: spark.range(10).selectExpr("no_such"), 60)


def test_shuffle_and_scale_out_are_measured(spark, small):
    costs = metrics.stage_costs(spark, lambda: spark.range(1000).repartition(4))
    assert costs["shuffle_written"] > 0 and costs["cpu_ns"] > 0 and costs["disk_spilled"] == 0
    assert metrics.stage_costs(spark, lambda: spark.range(10))["shuffle_written"] == 0
    assert metrics.scale_out(lambda r: bucketed.build(small, r=r), (1, 2))[1] == 1


def test_chunks_of_a_bucket_follow_its_blocks(spark):
    """With joined chunks no bucket reads further than its widest gap and k behind a member, whatever the text repeats, and the transform is whole."""
    r = random.Random(3)
    passage = "".join(r.choice("acgt") for _ in range(900))
    text = "".join(r.choice("acgt") for _ in range(3000)) + passage + "x" * 50 + passage
    c = corpus.literal(spark, text)
    rows = bucketed.partition(c, 2, 4, "histogram")
    size = 64
    need = {(x.bucket, x.chunk) for x in bucketed.chunks_needed(cut(rows), c.n, 2, "gap_rename", size).collect()}
    own = {}
    for x in rows.collect():
        own.setdefault(x.bucket, []).append(x.pos)
    for b, pos in own.items():
        reach = partial.max_gap(np.array(pos), c.n) + 2
        assert {k for x, k in need if x == b} == {k for p in pos for k in range(max(p - 1, 0) // size, min(p + reach, c.n - 1) // size + 1)}
    old = bucketed.CHUNK_SYMBOLS
    try:
        bucketed.CHUNK_SYMBOLS = size
        for kernel in partial.KERNELS:
            built = bucketed.build(c, k=2, r=4, kernel=kernel, splitters="histogram", reader="chunk_join")
            assert positions(built) == sa_of(text)
            assert [r.code for r in built.orderBy("rank").collect()] == [r.code for r in bwt.from_suffix_array(built.select("rank", "pos"), c).orderBy("rank").collect()]
    finally:
        bucketed.CHUNK_SYMBOLS = old


def test_tables_written_inside_scratch_go(spark):
    import os

    from suffix_engine import session

    kept = session.written(spark.range(3), "kept")
    with session.scratch(spark):
        inside = session.written(spark.range(3), "inside").inputFiles()[0]
    path = kept.inputFiles()[0].removeprefix("file:")
    assert not os.path.exists(inside.removeprefix("file:")) and os.path.exists(path)
    session.clear(spark)
    assert not os.path.exists(path)


def test_searches_go_on_above_the_broadcast_bound(spark, monkeypatch):
    r = random.Random(8)
    c = corpus.literal(spark, "".join(r.choice("ACGT") for _ in range(300)))
    built = cut(bucketed.build(c))
    index = fm.build(built.select("rank", "code"), built.select("rank", "pos"), c, block=16, sample=4)
    patterns = spark.createDataFrame([(1, "AC"), (2, "GTA"), (3, "AX"), (4, ""), (1, "TTT"), (5, "ACGTACGTACGTA")], "pattern_id long, pattern string")
    found = lambda: (fm.count(index, patterns), fm.locate(index, fm.count(index, patterns.where("pattern <> ''"))), fm.count_approx(index, patterns, 1))
    want = [sorted(map(tuple, df.collect())) for df in found()]
    monkeypatch.setattr(fm, "BROADCAST_SYMBOLS", 100)
    assert [sorted(map(tuple, df.collect())) for df in found()] == want and len(want[1]) > 20


@pytest.mark.parametrize("order", ["smallest", "largest"])
def test_binary_search_takes_any_pattern(spark, order):
    r = random.Random(9)
    text = "".join(r.choice("ab") for _ in range(200)) + "ababab"
    c = corpus.literal(spark, text, order)
    words = ["", "a", "ab", "bbbbbbbbbbbbbbbbbbbb", "ax", text, text[3:150], text[-1:], text + "a", "a$"]
    patterns = spark.createDataFrame(list(enumerate(words)), "pattern_id long, pattern string")
    built = cut(bucketed.build(c))
    got = {r.pattern_id: (r.lo, r.hi, r.cnt) for r in suffix_array.binary_search(built.select("rank", "pos"), c, patterns, size=16).collect()}
    index = fm.build(built.select("rank", "code"), built.select("rank", "pos"), c, block=16, sample=4)
    assert got == {r.pattern_id: (r.lo, r.hi, r.cnt) for r in fm.count(index, patterns).collect()} and got[5][2] == 1


def test_words_of_all_lengths_are_patterns(spark):
    r = random.Random(10)
    text = "".join(r.choice("abcd") for _ in range(300))
    c = corpus.literal(spark, text)
    k = kmers.widest(c)
    words = [text[3:4], text[3:6], text[9 : 9 + k], text[9 : 10 + k], text[50 : 50 + 3 * k + 2], text[7 : 7 + k] + "a" * k, "x", "x" * 2 * k]
    got = kmers.lookup_any(c, spark.createDataFrame([(x,) for x in words], "word string")).collect()
    assert sorted(map(tuple, got)) == sorted((x, p) for x in set(words) for p in range(len(text)) if text.startswith(x, p))
    own = {r.pattern for r in queries._patterns(spark, "/root/testdata/sf0.001").collect()}
    assert {1, 2, 3, 6, 9} <= {len(x) for x in own} and max(map(len, own)) > 90


def test_golden_examples_over_a_table(spark, tmp_path):
    """The worked examples as rows of a table: both orders of the terminator, repeated, empty and null texts."""
    rows = [(4, "BANANA"), (2, "CATTATTAGGA"), (9, "BANANA"), (5, ""), (6, None), (7, "A\tB\nA$")]
    spark.createDataFrame(rows, "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    got = {(r.item_id, r.terminator): (r.sa, r.bwt, r.primary) for r in queries.queries()["golden_examples"](spark, str(tmp_path)).collect()}
    banana = {"smallest": ("6 5 3 1 0 4 2", "ANNB$AA", 4), "largest": ("1 3 5 0 2 4 6", "BNN$AAA", 3)}
    cat = {"smallest": ("11 10 7 4 1 0 9 8 6 3 5 2", "AGTTC$GATTAA", 5), "largest": ("7 4 1 10 0 9 8 6 3 5 2 11", "TTCG$GATTAAA", 4)}
    want = {(i, order): banana[order] for i in (4, 9) for order in banana} | {(2, order): cat[order] for order in cat} | {(5, order): ("0", "$", 0) for order in cat}
    own = {order: bwt.encode("A\tB\nA", order) for order in cat}
    assert {k: v for k, v in got.items() if k[0] != 7} == want and {k[1]: v[1:] for k, v in got.items() if k[0] == 7} == own


def test_shuffle_files_of_earlier_rounds_go(spark, monkeypatch):
    monkeypatch.setattr(session, "RELEASE_EVERY", 0.0, raising=False)
    blocks = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()

    def files():
        left = blocks.getAllFiles()
        return sum(left.apply(i).toString().endswith(".data") for i in range(left.size()))

    gc.collect()
    df = spark.range(20_000)
    before = files()
    for i in range(6):
        df = session.cut(df.repartition(4, (F.col("id") + i) % 7))
    for _ in range(50):
        if files() <= before + 8:
            break
        time.sleep(0.2)
    assert files() <= before + 8


@pytest.mark.parametrize("text", [TEXT, "a" * 3000, "ab" * 1500, "", "x", "abaab" * 700 + "b"])
@pytest.mark.parametrize("order", ["smallest", "largest"])
def test_inverse_by_walks_and_by_jumps(spark, monkeypatch, text, order):
    c = corpus.literal(spark, text, order=order)
    t = cut(bwt.from_suffix_array(bucketed.build(c, r=4).select("rank", "pos"), c))
    want = [(r.pos, r.code) for r in corpus.text(c).orderBy("pos").collect()]
    if text == TEXT:
        assert [tuple(r) for r in bwt.invert(t, c, most=1).orderBy("pos").collect()] == want
    # no joins of all rows: a round for each power of two took most of the time
    monkeypatch.setattr(bwt, "invert_by_jumps", None)
    for step in (1, 8, 1024):
        assert [tuple(r) for r in bwt.invert(t, c, step=step).orderBy("pos").collect()] == want


def test_inverse_of_what_is_no_transform(small, small_sa):
    t = bwt.from_suffix_array(small_sa, small)
    with pytest.raises(ValueError):
        bwt.invert(t.where("rank > 3"), small)
    with pytest.raises(ValueError):
        # every symbol once, but in an order with several cycles
        bwt.invert(t.withColumn("rank", F.when(F.col("rank") == 9, 200).when(F.col("rank") == 200, 9).otherwise(F.col("rank"))), small)


def test_words_are_looked_up_in_the_text_itself(spark, small, monkeypatch):
    words = ["the", "t", "at", "sat on the mat", "zzzz", "tail", "é", "q", "$", "", "a cat", TEXT[3:80], "xq" * 9, "tail" + "l" * 9]
    rows = spark.createDataFrame([(x,) for x in [*words, "the"]], "word string")
    want = sorted((x, i) for x in words if x for i in range(len(TEXT)) if TEXT.startswith(x, i))
    assert sorted(tuple(r) for r in kmers.lookup_any(small, rows, most=0).collect()) == want
    # the index of all k-mers was shuffled once for each length
    monkeypatch.setattr(kmers, "hash_index", None)
    assert sorted(tuple(r) for r in kmers.lookup_any(small, rows).collect()) == want
    assert kmers.lookup_any(small, rows.limit(0)).collect() == []


@pytest.mark.parametrize("pairing", ["block", "join"])
def test_the_estimated_size_does_not_grow_with_the_rounds(spark, pairing):
    c = corpus.literal(spark, "abcab" * 60)
    ranks, h = cut(doubling.init_ranks(c)), 1
    for _ in range(4):
        ranks = cut(doubling.one_round(ranks, h, pairing, "distinct"))
        h *= 2
        assert ranks._jdf.queryExecution().logical().stats().sizeInBytes() <= 2**63 - 1
    assert {tuple(x) for x in ranks.select("pos", "rnk").collect()} == {tuple(x) for x in doubling.build(c, pairing, "distinct", rounds=4, h0=1).ranks.collect()}


def test_a_bounded_checkpoint_keeps_rows_and_their_partitions(spark):
    big = spark.range(40).withColumn("x", F.col("id") % 7)
    for name in "abcdefghij":
        big = big.join(spark.range(40).withColumnRenamed("id", name), F.col("id") == F.col(name))
    kept = cut_by(big.select("id", "x"), "id")
    assert sorted(tuple(r) for r in kept.collect()) == [(i, i % 7) for i in range(40)]
    assert kept._jdf.queryExecution().logical().stats().sizeInBytes() <= 2**63 - 1
    assert kept._jdf.queryExecution().logical().outputPartitioning().toString().startswith("hashpartitioning(id")


def test_a_checkpoint_of_numbers_is_small_and_keeps_its_partitions(spark):
    stored = lambda: sum(f.stat().st_size for f in Path(spark.conf.get("spark.checkpoint.dir")).rglob("rdd-*/part-*"))
    rows = spark.range(20000).select("id", (F.col("id") * 7919 % 20011).alias("x"), (F.col("id") % 2 == 0).alias("even"), F.when(F.col("id") > 5, F.col("id") / 2).alias("half"))
    gc.collect()
    before = stored()
    held = session.cut_numbers(rows.repartitionByRange(5, "x").sortWithinPartitions("x"))
    assert stored() - before < 20000 * 10
    assert held.schema == rows.schema and held.exceptAll(rows).count() == 0 and held.count() == 20000
    by = {}
    for r in held.select(F.spark_partition_id().alias("p"), "x").collect():
        by.setdefault(r.p, []).append(r.x)
    assert len(by) == 5 and [x for p in sorted(by) for x in by[p]] == sorted(r.x for r in rows.collect())
    assert session.cut_numbers(rows.where("id < 0")).count() == 0
    words = spark.createDataFrame([("a",), (None,)], "t string")
    assert session.cut_numbers(words).exceptAll(words).count() == 0


@pytest.mark.parametrize("alone,order", [(1 << 23, "smallest"), (40, "largest")])
def test_buckets_in_turns(spark, monkeypatch, alone, order):
    from dataclasses import replace

    from suffix_engine.operators import anchors

    monkeypatch.setattr(anchors, "ALONE", alone)
    r = random.Random(4)
    base = "".join(r.choice("ab") for _ in range(900))
    c = corpus.literal(spark, base + base[:700] + "c" + base + "a" * 90, order)
    want = sa_of(base + base[:700] + "c" + base + "a" * 90, order)
    turns = anchors.turns(c, 3, 6, 128)
    assert turns.count == 3 and turns.buckets > 3
    rows = lambda b, pos, first, before: pa.table({"bucket": np.full(len(pos), b), "ord": np.arange(len(pos)), "pos": pos})
    # no turn has all suffixes, and together they have each once
    got = [turns.each(t, rows, "bucket long, ord long, pos long").collect() for t in range(3)]
    assert max(map(len, got)) < len(want)
    assert [r.pos for part in got for r in sorted(part)] == want
    n = len(want)
    assert tuple(verify.check_turns(turns, c).first()) == (n, n, n, 0, 0)

    class Wrong(anchors.Turns):
        def each(self, turn, f, schema):
            def swapped(b, pos, first, before):
                i = next((i for i in range(len(pos) - 1) if first[i] == first[i + 1]), 0)
                own = np.arange(len(pos))
                own[i : i + 2] = own[i : i + 2][::-1]
                return f(b, pos[own], first[own], before[own])

            return super().each(turn, swapped, schema)

    assert verify.check_turns(Wrong(turns.known, turns.shape, turns.borders, turns.count, turns.end), c) is None
    assert verify.check_turns(replace(turns, borders=turns.borders[:-1], count=2), c) is not None


def test_digests_tell_sequences_apart():
    p = verify.PRIME
    a, b = np.array([p - 1, 5, 1 << 60], np.uint64), np.array([p - 1, p - 2, 12345678901234567], np.uint64)
    assert verify.times(a, b).tolist() == [int(x) * int(y) % p for x, y in zip(a.tolist(), b.tolist(), strict=True)]
    code, values = np.array([1, 0, 1, 1]), np.array([7, 3, 8, 9])
    assert verify.digests(code, values, (10,)) == [(0, 1, 3), (1, 3, 7 + 80 + 900)]
    assert verify.digests(code, np.array([7, 3, 9, 8]), (10,))[1] != verify.digests(code, values, (10,))[1]


@pytest.mark.parametrize("name,n", [("english", 316488), ("dna", 376806), ("proteins", 376806)])
def test_whole_texts_are_inverted(spark, name, n):
    sf = "/root/testdata/sf0.001"
    assert [tuple(r) for r in queries.queries()[f"check_{name}_inverse"](spark, sf).collect()] == [(n, n, 0)]
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    assert con.execute(queries.oracle_sql()[f"check_{name}_inverse"]).fetchall() == [(n, n, 0)]


@pytest.mark.parametrize("name", ["check_dna_refine", "check_english_refine", "check_proteins_refine", "check_dna_histogram", "check_dna_orderby"])
def test_texts_over_the_bound_are_sorted_in_turns(spark, monkeypatch, name):
    r = random.Random(9)
    base = "".join(r.choice("acgt") for _ in range(3000))
    c = corpus.literal(spark, base + base[:2000] + "aaaa" * 40)
    monkeypatch.setattr(bucketed, "BROADCAST_SYMBOLS", 1000)
    monkeypatch.setattr(queries.w, name.split("_")[1], lambda spark, d: c)
    with monkeypatch.context() as m:
        m.setattr(bucketed, "build", None)  # no table of all positions
        assert tuple(queries.queries()[name](spark, "").first()) == (c.n, c.n, c.n, 0, 0)
    splitters = name.split("_")[2]
    options = {"splitters": splitters} if splitters != "refine" else {}
    built = bucketed.build(c, k=3, r=6, **options)
    assert [x.pos for x in built.orderBy("rank").collect()] == sa_of(base + base[:2000] + "aaaa" * 40)


def test_borders_of_buckets(spark):
    c = corpus.literal(spark, "ACGT" * 700 + "A" * 1200)
    keys = sorted(x[0] for x in kmers.extract(c, 3).collect())
    for splitters in ("histogram", "orderby"):
        found = bucketed.borders(c, 3, 4, splitters) >> kmers.bits(c) * (kmers.widest(c) - 3)
        assert 1 <= len(found) <= 3 and sorted(found) == list(found) and set(found) < set(keys)
        # no bucket has more than two even shares and its last k-mer
        sizes = np.diff(np.r_[0, np.searchsorted(keys, found), len(keys)])
        assert sizes.min() > 0 and sizes.max() <= 2 * len(keys) // 4 + max(keys.count(k) for k in set(keys))


@pytest.mark.parametrize("order", ["smallest", "largest"])
def test_transform_in_turns(spark, monkeypatch, order):
    r = random.Random(11)
    base = "".join(r.choice("abcd") for _ in range(2000))
    text = base + base[:1500] + "z" + "a" * 70
    c = corpus.literal(spark, text, order)
    monkeypatch.setattr(queries.w, "english", lambda spark, d: c)
    with monkeypatch.context() as m:
        m.setattr(bucketed, "BROADCAST_SYMBOLS", 1000)
        m.setattr(bucketed, "build", None)  # no table of all positions
        t = bucketed.transform(c, count=3, r=6)
        assert [x.rank for x in t.orderBy("rank").collect()] == list(range(c.n))
        assert bwt.as_string(t, c) == bwt.encode(text, order)[0]
        found = {x["of"]: (x.n, x.bits) for x in queries.queries()["bwt_mtf_entropy"](spark, "").collect()}
    built = bucketed.build(c, reader="broadcast").select("rank", "code")
    own, symbols, moved = built.orderBy("rank").collect(), list(range(c.sigma)), []
    for x in own:
        moved.append(symbols.index(x.code))
        symbols.insert(0, symbols.pop(moved[-1]))
    shares = np.unique(moved, return_counts=True)[1] / c.n
    assert found["transform"] == (c.n, pytest.approx(-(shares * np.log2(shares)).sum()))
    assert found["text"] == (c.n, pytest.approx(compress.entropy(built, "code").first().bits))


def test_move_to_front_of_rows_in_any_order(spark):
    codes = [0, 0, 3, 3, 3, 1, 0, 2, 2, 300, 300, 0] * 9
    rows = spark.createDataFrame([(i, c) for i, c in enumerate(codes)], "rank long, code int").orderBy(F.xxhash64("rank"))
    want = []
    for i, c in enumerate(codes):
        symbols = list(range(301)) if i % 8 == 0 else symbols
        want.append(symbols.index(c))
        symbols.insert(0, symbols.pop(want[-1]))
    m = cut(compress.mtf(rows, 301, 8))
    assert [x.mtf for x in m.orderBy("rank").collect()] == want
    assert [x.code for x in compress.mtf(m, 301, 8, inverse=True).orderBy("rank").collect()] == codes


@pytest.mark.parametrize("rounds,h,pairing,rerank", [("paper", 1, "union_reduce", "global"), ("early_stop", 3, "union_reduce", "global"), (3, 1, "union_reduce", "global"), ("paper", 1, "join", "group"), (8, 5, "join", "group")])
def test_packed_rounds_are_the_rounds_of_rows(spark, monkeypatch, rounds, h, pairing, rerank):
    r = random.Random(5)
    base = "".join(r.choice("ab") for _ in range(400))
    text = base + "a" * 60 + base[:333]
    c = corpus.literal(spark, text)
    packed = doubling.build_packed(c, rounds, h, pairing, rerank, block=64, ranges=5)
    monkeypatch.setattr(doubling, "build_packed", None)
    monkeypatch.setattr(doubling, "MOST_PACKED", 1)
    rows = doubling.build(c, pairing, rerank, rounds, h, active_only=False)
    assert packed.ranks.exceptAll(rows.ranks).count() == 0 and packed.ranks.count() == c.n
    of = lambda result: [(x.number, x.reach, x.groups, x.unresolved, x.rows) for x in result.rounds]
    assert of(packed) == of(rows)
    if rounds != 3:
        assert ranks(packed.ranks) == sa_of(text)


def test_published_rounds_move_blocks_of_ranks(spark, monkeypatch):
    # a round over rows sends each rank as a row of its own
    monkeypatch.setattr(doubling, "one_round", None)
    for text in ("", "a", "BANANA" * 30):
        assert ranks(queries._published(corpus.literal(spark, text)).ranks) == sa_of(text)
    literal = queries._variants()["doubling_literal_rounds"](corpus.literal(spark, "BANANA" * 30))
    assert [x.pos for x in literal.orderBy("rank").collect()] == sa_of("BANANA" * 30)


def test_letters_of_texts(spark, tmp_path):
    texts = ["Abc-xyz", None, "", "É$ßK İzZ\n09 aä\U0001f600b", "x" * 50, "ſ"]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows.repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    letters = "abcdefghijklmnopqrstuvwxyz"
    for alphabet in (queries.w.NUCLEOTIDES, queries.w.AMINO_ACIDS):
        want = rows.select("doc_id", F.translate(F.regexp_replace(F.lower("text"), "[^a-z]", ""), letters, (alphabet * 26)[:26]).alias("text"))
        got = queries.w.letters_rows(spark, str(tmp_path), alphabet)
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
        assert got.where("text is null").count() == 1
        assert queries.w.letters_rows(spark, str(tmp_path), alphabet).where("doc_id < 0").count() == 0
