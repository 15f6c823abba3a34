import hashlib
import random
import zlib

import brute
import public_tokenizers
import pytest

from suffix_engine.llm import decontaminate, media, tokens, urls

SF = "/root/testdata/sf0.001"


def test_token_counts_equal_the_library(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    texts = ["", None, "<|endoftext|>", "a<|endoftext|> b<|endoftext|><|endoftext|>", "  two  spaces \n\n x\u3000y \U0001f600 日本語 'll don't it's '''s", "\x1c\x1d a\x85b\u200b \ufeff", "x" * 50000, " " * 3000 + "\t\t\n", "ΑΒΓ١٢٣ Ⅷ²½ é e\u0301", "word " * 20000]
    odd = spark.createDataFrame([(10_000 + i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    both = docs.unionByName(odd)
    path = public_tokenizers.path("byte_bpe_50k.json")
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(path)
    got = {r.doc_id: (r.n_bytes, r.n_tokens, r.over_limit) for r in tokens.token_report(both, path).collect()}
    for d, t in both.collect():
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        assert got[d] == (len((t or "").encode()), n, n > 1024)
    assert tokens.token_report(both.limit(0), path).collect() == []


def test_every_character_counts_as_in_the_library():
    with open(public_tokenizers.path("byte_bpe_50k.json"), encoding="utf-8") as f:
        source = f.read()
    counter = tokens.Counter(source, tokens.prove_whole_tokens(source))
    for low in range(0, 0x11000, 97):
        chars = [chr(c) for c in range(low, low + 97) if not 0xD800 <= c < 0xE000]
        text = " ".join(f"a{c}1{c}{c} {c}" for c in chars)
        assert counter.count(text) == len(counter.library.encode(text, add_special_tokens=False))
    small = tokens.MEMO
    try:
        tokens.MEMO = 0
        assert counter.count("zqxv qqq zzz9 zqxv") == len(counter.library.encode("zqxv qqq zzz9 zqxv", add_special_tokens=False))
    finally:
        tokens.MEMO = small


@pytest.mark.parametrize("bound", [64 << 20, 50])
def test_contamination(spark, monkeypatch, bound):
    monkeypatch.setattr(decontaminate, "AUTOMATON_BYTES", bound)
    rows = brute.sample_texts(7)
    text = rows[20][1].split()
    items = [("b", " ".join(text[:30])), ("a", " ".join(text[5:25])), ("c", "abc, É!"), ("d", ""), ("e", None), ("b", "zz yy " * 8), ("f", rows[30][1]), ("g", "ha " * 400), ("h", " ".join(text[:13])), ("i", "ab " * 7 + "cd " * 7)]
    rows += [(510, "ha " * 12), (511, "ha " * 13 + "no " * 30), (512, "ha " * 3000), (513, "ab " * 40 + "cd " * 6), (514, "ab " * 8 + "cd " * 9), (515, " ".join(text[6:19])), (516, " ".join(text[6:18]))]
    rows += [(500, "x " * 300 + " ".join(text[2:17]) + " y" * 200), (501, "ABC! é."), (502, "abc é"), (503, "ABC\u00a0É")]
    docs = spark.createDataFrame([(*r, "k") for r in rows], "doc_id long, text string, items string")
    bench = spark.createDataFrame([(*i, 1) for i in items], "item_id string, text string, doc_id int")
    got = {r[0]: tuple(r[1:]) for r in decontaminate.contamination(docs, bench).collect()}
    want = brute.contaminated(rows, items)
    assert got == want
    kept = decontaminate.clean(docs, bench)
    assert {r.doc_id for r in kept.collect()} == {d for d, w in want.items() if not w[4]} and kept.columns == docs.columns
    for r in decontaminate.with_spans(docs, bench).where("doc_id = 500").collect():
        assert [dict(rows)[500][s.begin : s.end] for s in r.spans] == [" ".join(text[2:17])]
    assert not any(r.contaminated for r in decontaminate.contamination(docs, bench.limit(0)).collect())
    assert decontaminate.contamination(docs.limit(0), bench).collect() == []


@pytest.mark.parametrize("size", [1, 2, 5, 13])
def test_blocks_and_contexts_find_what_windows_find(size):
    r = random.Random(size)
    word = lambda: r.choice("abc")
    items = [(str(i), " ".join(word() for _ in range(r.randint(0, 40)))) for i in range(12)]
    rows = [(i, " ".join(word() for _ in range(r.randint(0, 120)))) for i in range(40)]
    index = decontaminate.Items(items, size)
    want = brute.contaminated(rows, items, size)
    for d, t in rows:
        spans, own = index.occurrences(f" {t} ")
        assert (sum(z - a for a, z in spans), len(own), brute.sha(",".join(sorted(own)))) == want[d][1:4]


def test_contamination_of_repeated_rows_and_long_texts(spark):
    item = " ".join(f"w{i}" for i in range(20))
    docs = spark.createDataFrame([(1, item)] * 3 + [(None, item), (2, "pad " * 200_000 + item)], "doc_id long, text string")
    bench = spark.createDataFrame([(7, item), (7, item), (None, item)], "item_id int, text string")
    got = [tuple(r) for r in decontaminate.contamination(docs, bench).select("n_words", "n_hit", "n_items", "contaminated").collect()]
    assert sorted(got) == [(20, 20, 2, True)] * 4 + [(200_020, 20, 2, False)]


def test_a_worker_does_not_mix_up_benchmarks(spark):
    docs = spark.createDataFrame([(1, "one two three")], "doc_id long, text string").coalesce(1)
    for key in ("a", "b"):
        bench = spark.createDataFrame([(key, "two three")], "item_id string, text string")
        assert [r["items"] for r in decontaminate.scan(docs, bench).collect()] == [[key]]


def test_media_round_trip(spark):
    texts = [None, "", "a", "x" * 64, "x" * 65, "é\0" * 5000, "x" * 64, "long " * 60000]
    docs = spark.createDataFrame([(i, t, "h") for i, t in enumerate(texts)] + [(None, "a", "h")], "doc_id long, text string, html string")
    got = media.document_media(docs).collect()
    assert len(got) == len(texts) + 1
    for r in got:
        raw = ("a" if r.doc_id is None else texts[r.doc_id] or "").encode()
        payload = raw.ljust(max(64, -(-len(raw) // 64) * 64), b"\0")
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        stored = media.encode_image(payload)
        assert (r.media_bytes, r.media_sha256, r.feature) == (len(stored), hashlib.sha256(stored).hexdigest(), media.feature(payload)) and media.decode_image(stored) == payload
    assert media.document_media(docs.limit(0)).collect() == []


def test_damaged_media_is_refused():
    stored = bytearray(media.encode_image(b"x" * 128))
    stored[45] ^= 1
    with pytest.raises(ValueError):
        media.decode_image(bytes(stored))


def test_sequences_stay_aligned(spark):
    html = '<body><h1>T &amp; t</h1>a<figure><figcaption>first <b>cap</b></figcaption><img src="sha256:aa" alt="x"></figure><script>no</script><p>b <img src="bb" alt="two"> c</p><img><figure>t<figcaption>alone</figcaption></figure><video src="aa"></video>'
    items = media.read_html(html)
    assert [(x["pos"], x["kind"], x["text"], x["digest"], x["caption"]) for x in items] == [(0, "text", "T & t", None, None), (1, "text", "a", None, None), (2, "image", None, "aa", "first cap"), (3, "text", "b", None, None), (4, "image", None, "bb", "two"), (5, "text", "c", None, None), (6, "text", "t", None, None), (7, "text", "alone", None, None), (8, "video", None, "aa", None)]
    pages = spark.createDataFrame([(1, html, "x"), (2, None, "y"), (3, "<p", "z"), (1, html, "x")], "page_id long, html string, digest string")
    seq = media.sequences(pages, "page_id", "html")
    assert seq.count() == 4
    out = media.resolve(seq, "page_id", spark.createDataFrame([("aa", 5)], "digest string, media_bytes long")).where("page_id = 1 and digest is not null").collect()
    assert sorted((r.pos, r.media_bytes) for r in out) == [(2, 5), (2, 5), (4, None), (4, None), (8, 5), (8, 5)]


URLS = ["http://Example.COM/en/1?x#y", "https://www.example.com/en/2", "http://a.www.example.com/en/", "http://x.example.net/es/1", "x.net/fr/", None, "", "://", "ftp://net/fr", "http://net/fr/", "http://anet/fr/", "http://b.org", "http://example.com:80/en/3", "a://b://c/d", "http://q.com?x=/en/", "http://www.example.com/de/1"]


def rule_of(url):
    host, path = "", ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        ends = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
        host, path = rest[:ends].translate(brute.LOWER), rest[ends:].split("?")[0].split("#")[0]
    best = max(((h + p, v) for h, p, v in urls.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)), key=lambda x: len(x[0]), default=(None, None))
    return host, path, *best


def test_rules(spark):
    pages = spark.createDataFrame([(i, u, "h", "r") for i, u in enumerate(URLS)], "page_id long, url string, host string, rule string")
    for r in urls.judge(pages).collect():
        host, path, rule, verdict = rule_of(URLS[r.page_id])
        assert (r.host, r.path, r.rule) == (host, path, rule) and r.verdict == (verdict or "allow")
    assert urls.judge(pages.limit(0)).collect() == []


def test_templates_and_purity(spark):
    rows = [(f"/a/{i}/x", int(i < 30)) for i in range(40)] + [(f"/b/{i}", 1) for i in range(30)] + [("/c/d/e/f/g", 0)] * 3 + [("", None), ("/", None)]
    pages = spark.createDataFrame([("h", p, b) for p, b in rows] + [("other", "/b/1", None)], "host string, path string, blocked int")
    t = urls.templates(pages, branches=16, depth=4)
    got = {(r.path, r.template) for r in t.where("host = 'h'").collect()}
    assert got == {(f"/a/{i}/x", "/a/*/x") for i in range(40)} | {(f"/b/{i}", "/b/*") for i in range(30)} | {("/c/d/e/f/g", "/c/d/e/f/**"), ("", ""), ("/", "")}
    bad = {(r.host, r.template) for r in urls.rejected_templates(t).collect()}
    assert bad == {("h", "/b/*")}  # 30 of 30, smoothed; 30 of 40 is under the limit


def test_alike_branches_merge_and_take_unlabelled_ones_along(spark):
    long = "/z" * 40000
    rows = [(f"/b/{i}", 1) for i in range(10)] + [("/b/new", None), ("/b/fine", 0), ("/b/fine", 0), ("/b/fine", 0)] + [(f"/few/{i}", 1) for i in range(3)] + [("/few/new", None)] + [("/ok/1", 0)] * 9 + [(long, None)] * 2
    pages = spark.createDataFrame([(i, f"http://{p[1]}.org{p}") for i, (p, _) in enumerate(rows)], "page_id long, url string")
    labels = spark.createDataFrame([(i, b) for i, (_, b) in enumerate(rows)] + [(None, 1), (0, None)], "page_id long, blocked int")
    got = {rows[r.page_id][0]: (r.template, r.verdict) for r in urls.judge(pages, labels=labels).collect()}
    assert got["/b/new"] == got["/b/3"] == ("/b/*", "block") and got["/b/fine"] == ("/b/fine", "allow")
    assert got["/few/new"] == ("/few/new", "allow") and got["/few/1"][0] == "/few/*" and got["/ok/1"] == ("/ok/1", "allow")
    assert got[long][1] == "allow"
    # without labels nothing is learned, and all is allowed
    assert {r.verdict for r in urls.judge(pages).collect()} == {"allow"}


def test_rules_of_one_length_are_tried_in_order_and_repeated_pages_stay(spark):
    pages = spark.createDataFrame([(1, "http://a.b/c/")] * 3 + [(None, None)] * 2, "page_id long, url string")
    got = urls.judge(pages, rules=(("a.b", "/c/", "allow"), ("a.b", "/c/", "block"))).collect()
    assert sorted((r.page_id or 0, r.verdict) for r in got) == [(0, "allow")] * 2 + [(1, "allow")] * 3


def test_given_pages(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    rows = {r.page_id: r.url for r in pages.select("page_id", "url").collect()}
    got = urls.judge(pages).collect()
    assert len(got) == len(rows)
    for r in got:
        host, path, rule, verdict = rule_of(rows[r.page_id])
        assert (r.host, r.path, r.rule) == (host, path, rule) and r.verdict in ("allow", "block") and (verdict is None or r.verdict == verdict)


def plain_png(stored):
    """Samples of an 8-bit grey image by the public format alone, with all five row filters."""
    assert stored[:8] == bytes([137, 80, 78, 71, 13, 10, 26, 10])
    at, body, head = 8, b"", None
    while at < len(stored):
        size = int.from_bytes(stored[at : at + 4], "big")
        kind, data = stored[at + 4 : at + 8], stored[at + 8 : at + 8 + size]
        assert zlib.crc32(kind + data) == int.from_bytes(stored[at + 8 + size : at + 12 + size], "big")
        head, body = (data if kind == b"IHDR" else head), body + (data if kind == b"IDAT" else b"")
        at += 12 + size
    width, height = int.from_bytes(head[:4], "big"), int.from_bytes(head[4:8], "big")
    assert head[8:] == bytes([8, 0, 0, 0, 0])
    raw, above, out = zlib.decompress(body), bytes(width), bytearray()
    for y in range(height):
        kind, row = raw[y * (width + 1)], bytearray(raw[y * (width + 1) + 1 : (y + 1) * (width + 1)])
        for x in range(width):
            a, b, c = row[x - 1] if x else 0, above[x], above[x - 1] if x else 0
            near = min((abs(b - c), 0, a), (abs(a - c), 1, b), (abs(a + b - 2 * c), 2, c))[2]
            row[x] = (row[x] + (0, a, b, (a + b) // 2, near)[kind]) % 256
        above = bytes(row)
        out += above
    return bytes(out)


def test_stored_media_are_images_of_the_public_format():
    for payload in (b"\0" * 64, bytes(range(256)) * 2, "é\n".encode() * 64):
        assert plain_png(media.encode_image(payload)) == payload == media.decode_image(media.encode_image(payload))


def test_sequences_of_given_pages(spark):
    """Titles, headings and paragraphs come in the order of the page, without scripts and styles."""
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    html = {r.page_id: r.html for r in pages.collect()}
    for r in media.sequences(pages, "page_id", "html").collect():
        texts = [x.text for x in r.sequence if x.kind == "text"]
        assert [x.pos for x in r.sequence] == list(range(len(r.sequence))) and texts
        assert not any("track(" in t or "margin:0" in t for t in texts)
        title = html[r.page_id].split("<title>")[1].split("</title>")[0] if "<title>" in html[r.page_id] else None
        assert title is None or "&" in title or texts[0] == " ".join(title.split())


def test_token_counts_of_repeated_rows_and_clashing_columns(spark):
    docs = spark.createDataFrame([(1, "two words", 5, "x")] * 2 + [(None, None, None, None)], "doc_id long, text string, n_tokens int, n_bytes string")
    got = sorted((r.n_bytes, r.n_tokens) for r in tokens.token_report(docs, public_tokenizers.path("byte_bpe_50k.json")).collect())
    assert got[0] == (0, 0) and got[1] == got[2] and got[1][0] == 9
