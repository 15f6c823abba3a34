"""The kernels on one bucket, and the encoder, against sorted suffixes."""

import random
import tracemalloc

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from suffix_engine.operators import bwt, kmers, naive as baselines, partial

GOLDEN = [
    ("BANANA", "smallest", [6, 5, 3, 1, 0, 4, 2], "ANNB$AA", 4),
    ("BANANA", "largest", [1, 3, 5, 0, 2, 4, 6], "BNN$AAA", 3),
    ("CATTATTAGGA", "smallest", [11, 10, 7, 4, 1, 0, 9, 8, 6, 3, 5, 2], "AGTTC$GATTAA", 5),
    ("CATTATTAGGA", "largest", [7, 4, 1, 10, 0, 9, 8, 6, 3, 5, 2, 11], "TTCG$GATTAAA", 4),
]


def codes_of(text, order="smallest"):
    symbols = sorted(set(text))
    if order == "smallest":
        return np.array([symbols.index(c) + 1 for c in text] + [0], np.int64), len(symbols) + 1
    return np.array([symbols.index(c) for c in text] + [len(symbols)], np.int64), len(symbols) + 1


def naive(codes):
    return sorted(range(len(codes)), key=lambda i: tuple(codes[i:]))


def whole_sort(codes, sigma, k, r, kernel, reduction="gap_rename", length=None):
    """Buckets by ranges of k-mers, each sorted by the kernel, one after another."""
    n, width = len(codes), int(sigma).bit_length()
    keys = kmers.pack(codes, n, k, width)
    cuts = np.quantile(keys, np.linspace(0, 1, r + 1)[1:-1], method="nearest") if r > 1 else []
    bucket = np.searchsorted(cuts, keys, side="right")
    read, out = partial.array_reader(codes), []
    for b in range(r):
        own = np.flatnonzero(bucket == b)
        out += partial.sort_bucket(own, keys[own], read, n, k, width, kernel, reduction, length).tolist()
    return out


@pytest.mark.parametrize("text,order,sa,transform,primary", GOLDEN)
def test_golden(text, order, sa, transform, primary):
    codes, sigma = codes_of(text, order)
    assert naive(codes) == sa
    assert np.argsort(bwt.local_ranks(codes)).tolist() == sa
    assert bwt.encode(text, order) == (transform, primary)
    assert bwt.decode(transform, primary, order) == text
    for kernel in partial.KERNELS:
        for reduction in partial.REDUCTIONS:
            assert whole_sort(codes, sigma, 3, 4, kernel, reduction) == sa


def strings():
    r = random.Random(5)
    yield from ["", "a", "aaaaaaaaaa", "abababababab", "abaababaabaababaababa", "\n $!a é\U0001f600$"]
    for _ in range(60):
        yield "".join(r.choice("abcd"[: r.randint(1, 4)]) for _ in range(r.randint(0, 60)))


@pytest.mark.parametrize("kernel", partial.KERNELS)
@pytest.mark.parametrize("order", ["smallest", "largest"])
def test_kernels_equal_sorted_suffixes(kernel, order):
    r = random.Random(1)
    for text in strings():
        codes, sigma = codes_of(text, order)
        for k in (1, 2, 5):
            assert whole_sort(codes, sigma, k, r.randint(1, 6), kernel) == naive(codes)


def test_blocks_of_the_gap_alone_are_wrong():
    """Blocks must be longer than the widest gap by k - 1."""
    codes, sigma = codes_of("BABABBABABABB")
    n, width = len(codes), int(sigma).bit_length()
    keys = kmers.pack(codes, n, 2, width)
    wrong = 0
    for low in np.unique(keys):
        for high in np.unique(keys):
            own = np.flatnonzero((keys >= low) & (keys <= high))
            if len(own):
                gap = partial.max_gap(own, n)
                right = [p for p in naive(codes) if p in set(own.tolist())]
                read = partial.array_reader(codes)
                assert partial.sort_bucket(own, keys[own], read, n, 2, width, "merge").tolist() == right
                wrong += partial.sort_bucket(own, keys[own], read, n, 2, width, "merge", length=gap).tolist() != right
    assert wrong


def test_zero_padding_without_a_terminator_is_wrong():
    """Why the terminator is always appended: ranks that read 0 past the end and for the least symbol mix the two up."""
    codes = np.array([1, 1, 0, 0])  # BBAA
    rank, h = np.searchsorted(np.sort(codes), codes).astype(np.int64), 1
    while h < 4:
        key = rank * 10 + np.r_[rank[h:], np.zeros(h, np.int64)]
        rank, h = np.searchsorted(np.sort(key), key).astype(np.int64), 2 * h
    assert np.argsort(rank, kind="stable").tolist() != naive(codes)


def test_block_traces():
    codes, sigma = codes_of("CATTATTAGGA")
    for members, gap, ordered in [([10, 11], 1, [11, 10]), ([1, 4, 7], 5, [7, 4, 1]), ([0, 8, 9], 8, [0, 9, 8]), ([2, 3, 5, 6], 6, [6, 3, 5, 2])]:
        own = np.array(members)
        assert partial.max_gap(own, 12) == gap and partial.block_length(own, 12, 3) == gap + 2
        keys = kmers.pack(codes, 12, 3, int(sigma).bit_length())[own]
        for kernel in partial.KERNELS:
            assert partial.sort_bucket(own, keys, partial.array_reader(codes), 12, 3, int(sigma).bit_length(), kernel).tolist() == ordered


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet=st.characters(exclude_categories=("Cs",)), max_size=60), st.sampled_from(["smallest", "largest"]))
def test_round_trip(text, order):
    transform, primary = bwt.encode(text, order)
    assert len(transform) == len(text) + 1 and bwt.decode(transform, primary, order) == text


def test_merge_kernel_copies_within_a_bound():
    """Many copies of one text tie for long: what is copied of them at once must not grow with both."""
    r = np.random.default_rng(3)
    codes = np.r_[np.tile(r.integers(1, 5, 2000), 10), 0]
    positions, read = np.arange(len(codes)), partial.array_reader(codes)
    tracemalloc.start()
    order = partial.merge_order(positions, read, len(codes))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert np.array_equal(order, np.argsort(bwt.local_ranks(codes))) and peak < 100e6


def test_whole_suffixes_are_compared_without_keeping_them():
    r = np.random.default_rng(4)
    codes = np.r_[np.tile(r.integers(1, 5, 500), 20), r.integers(1, 5, 10_000), 0]
    raw = codes.astype(">u2").tobytes()
    tracemalloc.start()
    order = baselines.whole_order(raw, np.arange(len(codes)))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert order == np.argsort(bwt.local_ranks(codes)).tolist() and peak < 10e6


@pytest.mark.parametrize("width", [1, 3, 5, 8, 9, 16])
def test_radix_passes_take_several_columns(monkeypatch, width):
    r = np.random.default_rng(width)
    most = min((1 << width) - 1, 60000)
    codes = np.append(r.integers(0, max(1, min(most, 4)), 400) * (most // 4), 0).astype(np.uint16)
    codes[100:250] = codes[200:350]
    read, positions = partial.array_reader(codes), np.sort(r.choice(401, 200, replace=False))
    passes, real = [], np.argsort
    monkeypatch.setattr(partial.np, "argsort", lambda *a, **k: passes.append(1) or real(*a, **k))
    for cells in (1, 1 << 22):
        monkeypatch.setattr(partial, "CELLS", cells)
        for length in (1, 7, 64, 203):
            passes.clear()
            got = partial.radix_order(positions, read, length, width)
            # one for each column before
            assert len(passes) == -(-length // (16 // width))
            rows = [read(positions[i : i + 1], 0, length)[0].tolist() for i in range(len(positions))]
            assert got.tolist() == sorted(range(len(positions)), key=lambda i: rows[i])


@pytest.mark.parametrize("width", [2, 3, 7, 17, 33])
def test_words_of_chunks_are_the_symbols_in_order(width):
    from suffix_engine.operators import anchors, partial

    r = np.random.default_rng(width)
    part = r.integers(1, min(1 << width, 1 << 40), 400)
    text = np.r_[part, part[:250], part[100:]]
    s = anchors.shape(len(text), width, names=width > 31, size=1 << 12)
    v = anchors.View(0, text, s)
    v = anchors.View(0, text, s, v.find())
    assert v.first == 0 and v.end == len(text)
    places, padded = np.arange(len(text)), np.r_[text, np.zeros(s.seen, np.int64)].tolist()
    columns = v.columns(places)
    want = [padded[i : i + s.seen] for i in places]
    order, place = partial.refine_columns([columns[f"w{j}"] for j in range(s.words)])
    assert [want[i] for i in order] == sorted(want)
    assert place.tolist() == [sorted(want).index(want[i]) for i in order]
    # suffixes alike as far as the words go have their anchors equally far off
    ahead, seen = v.anchors[v.number(places)] - places, {}
    assert ahead.min() >= 0 and ahead.max() < s.window
    for i in places:
        assert seen.setdefault(tuple(want[i]), ahead[i]) == ahead[i]
