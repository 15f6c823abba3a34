"""The queries over the given tables, whole tables and whole texts, and their SQL where SQL can say the same at that size."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from suffix_engine.operators import bucketed, bwt, compress, corpus, doubling, features, fm, hybrid, kmers, lcp, metrics, naive, partial, suffix_array, verify
from suffix_engine.operators import workloads as w
from suffix_engine.session import cut, cut_numbers
from suffix_engine.streaming import live

Query = Callable[[SparkSession, str], DataFrame]

def _golden(spark: SparkSession, d: str) -> DataFrame:
    """The worked example over every passage, with a terminator of its own, smallest or largest: array, transform and primary index, by the
    bucketed sort and by doubling, which must agree.

    All passages are sorted as one text, with separators that sort as the terminators do; passages have no U+0000 and no U+10FFFF.
    """
    out = None
    for order, separator in (("smallest", "\0"), ("largest", "\U0010ffff")):
        c = corpus.assemble(w.items_rows(spark, d), "item_id", "text", separator=separator, order=order)
        built = cut(bucketed.build(c, k=3, r=4))
        ranks = doubling.build(c, h0=1).ranks
        if built.join(ranks, "pos", "full").where("rank is distinct from rnk").limit(1).count():
            raise AssertionError("the bucketed sort and the doubling differ")
        placed = corpus.locate_documents(built, c).withColumn("start", F.col("pos") - F.col("offset"))
        shown = F.when(F.col("offset") == 0, F.lit(c.symbols[c.terminator])).otherwise(F.get(F.array(*(F.lit(x) for x in c.symbols)), F.col("code")))
        rows = placed.groupBy("key", "start").agg(F.array_sort(F.collect_list(F.struct("rank", "offset", shown.alias("s")))).alias("x"))
        offsets = F.transform("x", lambda x: x["offset"])
        mine = rows.select(F.col("key").alias("item_id"), F.lit(order).alias("terminator"), F.array_join(offsets.cast("array<string>"), " ").alias("sa"), F.array_join(F.transform("x", lambda x: x["s"]), "").alias("bwt"), (F.array_position(offsets, F.lit(0).cast("long")) - 1).alias("primary"))
        out = mine if out is None else out.unionByName(mine)
    return out


def _symbol_counts(spark: SparkSession, d: str) -> DataFrame:
    c = w.english(spark, d)
    rows = [(s, int(k), int(b)) for s, k, b in zip(c.symbols, c.counts, c.smaller, strict=True)]
    return spark.createDataFrame(rows, "symbol string, cnt long, smaller long")


def _kmer_histogram(spark: SparkSession, d: str) -> DataFrame:
    c = w.dna(spark, d)
    return kmers.readable(kmers.histogram(c, 4), c, 4).select("word", "cnt")


def _kmer_positions(spark: SparkSession, d: str) -> DataFrame:
    c = w.items(spark, d)
    return kmers.readable(kmers.extract(c, 5), c, 5).select("pos", "word")


def _kmer_lookup(spark: SparkSession, d: str) -> DataFrame:
    return kmers.lookup(w.english(spark, d), 6, _six(spark, d))


def _six(spark: SparkSession, d: str) -> DataFrame:
    """Words of six letters in the benchmark."""
    return w.items_rows(spark, d).select(F.explode(F.split("text", r"[^A-Za-z]+")).alias("word")).where("char_length(word) = 6").distinct()


def _patterns(spark: SparkSession, d: str, passages: bool = True) -> DataFrame:
    """(pattern_id, pattern): all words of the benchmark and of part names, and the passages."""
    words = w.items_rows(spark, d).select(F.explode(F.split("text", r"[^A-Za-z]+")).alias("pattern")).where("pattern <> ''")
    out = words.unionByName(w.word_patterns(spark, d).select("pattern"))
    if passages:
        out = out.unionByName(w.item_patterns(spark, d).select("pattern"))
    return out.where("pattern is not null").distinct().select(F.xxhash64("pattern").alias("pattern_id"), "pattern")


def _counted(index: Callable, count: Callable, passages: bool = True) -> Query:
    """(pattern, ...) of all patterns, whatever their length."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        patterns = cut(_patterns(spark, d, passages))
        return count(*index(spark, d), patterns).join(patterns, "pattern_id").drop("pattern_id", "lo", "hi")

    return run


def _property(spark: SparkSession, d: str) -> DataFrame:
    found = verify.bucket_property(bucketed.partition(w.dna(spark, d), 8, 16))
    return found.agg(F.bool_and("apart").alias("apart"), F.sum("members").alias("members"))


def _gaps(spark: SparkSession, d: str) -> DataFrame:
    """Buckets by first symbol."""
    c = w.english(spark, d)
    gaps = partial.bucket_gaps(corpus.text(c).withColumnRenamed("code", "bucket"), c.n)
    return gaps.select(F.get(F.array(*(F.lit(s) for s in c.symbols)), F.col("bucket")).alias("symbol"), "members", F.col("l_max").cast("long").alias("l_max"))


def _sorted_items(**options) -> Query:
    return lambda spark, d: bucketed.build(w.items(spark, d), **options).select("rank", "pos")


def _doubled_items(**options) -> Query:
    return lambda spark, d: doubling.build(w.items(spark, d), **options).ranks


def _rounds_of_items(n: int) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        ranks = doubling.init_ranks(w.items(spark, d))
        for i in range(n):
            ranks = cut(doubling.one_round(ranks, 1 << i))
        return ranks.select("pos", "rnk")

    return run


def _items_transform(spark: SparkSession, d: str) -> tuple:
    c = w.items(spark, d)
    built = cut(bucketed.build(c))
    return c, built.select("rank", "pos"), built.select("rank", "code")


def _bwt_from_sa(spark: SparkSession, d: str) -> DataFrame:
    c, sa, _ = _items_transform(spark, d)
    return bwt.symbols(bwt.from_suffix_array(sa, c), c)


def _primary(spark: SparkSession, d: str) -> DataFrame:
    c, sa, _ = _items_transform(spark, d)
    return sa.where("pos = 0").select(F.col("rank").alias("primary"))


def _inverse(spark: SparkSession, d: str) -> DataFrame:
    c, _, t = _items_transform(spark, d)
    symbols = F.array(*(F.lit(s) for s in c.symbols))
    return bwt.invert(t, c).select("pos", F.get(symbols, "code").alias("symbol"))


def _runs(spark: SparkSession, d: str) -> DataFrame:
    c, _, t = _items_transform(spark, d)
    return compress.rle(t, c.n).select("run", F.get(F.array(*(F.lit(s) for s in c.symbols)), "code").alias("symbol"), "start", "len")


def _english_index(spark: SparkSession, d: str) -> tuple:
    c = w.english(spark, d)
    built = cut(bucketed.build(c))
    return c, fm.build(built.select("rank", "code"), built.select("rank", "pos"), c), built


def _fm_count(spark: SparkSession, d: str) -> DataFrame:
    return fm.count(_english_index(spark, d)[1], w.item_patterns(spark, d)).select("pattern_id", "cnt")


def _fm_count_joined(spark: SparkSession, d: str) -> DataFrame:
    words = _six(spark, d).select(F.xxhash64("word").alias("pattern_id"), F.col("word").alias("pattern"))
    return fm.count_joined(_english_index(spark, d)[1], words).join(words, "pattern_id").select(F.col("pattern").alias("word"), "cnt")


def _fm_locate(spark: SparkSession, d: str) -> DataFrame:
    c, index, _ = _english_index(spark, d)
    found = fm.locate(index, fm.count(index, w.item_patterns(spark, d)))
    return corpus.locate_documents(found, c).select("pattern_id", F.col("key").alias("doc_id"), "offset")


def _sa_search(spark: SparkSession, d: str) -> DataFrame:
    c, sa, _ = _items_transform(spark, d)
    words = _six(spark, d).select(F.xxhash64("word").alias("pattern_id"), F.col("word").alias("pattern"))
    return suffix_array.binary_search(sa, c, words).join(words, "pattern_id").select(F.col("pattern").alias("word"), "cnt")


def _sa_search_passages(spark: SparkSession, d: str) -> DataFrame:
    """The benchmark's passages in the English text."""
    c = w.english(spark, d)
    return suffix_array.binary_search(bucketed.build(c).select("rank", "pos"), c, w.item_patterns(spark, d)).select("pattern_id", "cnt")


def _approx(spark: SparkSession, d: str) -> DataFrame:
    c, sa, t = _items_transform(spark, d)
    words = _six(spark, d).select(F.xxhash64("word").alias("pattern_id"), F.col("word").alias("pattern"))
    return fm.count_approx(fm.build(t, sa, c), words, 1).join(words, "pattern_id").select(F.col("pattern").alias("word"), "mismatches", "cnt")


def _lcp(spark: SparkSession, d: str) -> DataFrame:
    c, sa, _ = _items_transform(spark, d)
    return lcp.build(sa, c)


def _longest(spark: SparkSession, d: str) -> DataFrame:
    c = w.english(spark, d)
    return lcp.summary(lcp.build(bucketed.build(c).select("rank", "pos"), c), c.n)


def _longest_items(spark: SparkSession, d: str) -> DataFrame:
    c, sa, _ = _items_transform(spark, d)
    out = lcp.summary(lcp.build(sa, c), c.n)
    return out.select(F.col("longest_repeat").cast("long").alias("longest_repeat"), F.col("distinct_substrings").cast("long").alias("distinct_substrings"))


def _items_entropy(spark: SparkSession, d: str) -> DataFrame:
    """Order-0 entropy of the passages, and the runs of their transform."""
    c, _, t = _items_transform(spark, d)
    runs = compress.run_report(t, c.n)
    return compress.entropy(t, "code").join(F.broadcast(runs.select("runs")), how="inner").select("n", F.round("bits", 6).alias("bits"), F.col("runs").cast("long").alias("runs"))


def _checked(make) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        c = make[0](spark, d)
        return verify.check_suffix_array(cut_numbers(make[1](c)), c)

    return run


def _checked_in_turns(text: Callable, **options) -> Query:
    """_checked for a bucketed sort. Where it is made in turns, each bucket's order is checked as it is made and not kept. If anything is wrong, the
    array is built as a table, and what is wrong is counted."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        c = text(spark, d)
        turns = bucketed.turns(c, **options)
        found = None if turns is None else verify.check_turns(turns, c)
        return verify.check_suffix_array(cut_numbers(bucketed.build(c, **options).select("rank", "pos")), c) if found is None else found

    return run


#: Which part of a whole text the methods run over whose cost grows faster than the text, or that take a round for each power of two.
PART = 32


def _prefix(text: Callable) -> Callable:
    def run(spark: SparkSession, d: str) -> corpus.Corpus:
        c = text(spark, d)
        return corpus.prefix_of(c, c.n // PART)

    return run


def _published(c: corpus.Corpus) -> doubling.Result:
    """The doubling as published: ranks by one symbol, tagged union and reduce, global re-ranking by range, a fixed number of rounds."""
    return doubling.build(c, pairing="union_reduce", rerank="global", rounds="paper", h0=1, active_only=False)


def methods() -> dict[str, Callable[[corpus.Corpus], DataFrame]]:
    """The three that the published table compares."""
    return {
        "bucketed_radix": lambda c: bucketed.build(c, kernel="radix", r=64),
        "bucketed_merge": lambda c: bucketed.build(c, kernel="merge", r=64),
        "doubling": lambda c: _published(c).ranks,
    }


def _table(text: Callable, shares: tuple[int, ...] = (64, 32), limit: float = 40.0) -> Query:
    """Prefixes of growing size by the three methods: seconds (censored at the limit), and how often faster the doubling is."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        whole, rows = text(spark, d), []
        for share in shares:
            c = corpus.prefix_of(whole, whole.n // share)
            got = {name: metrics.timed(lambda make=make, c=c: make(c), limit) for name, make in methods().items()}
            rows += [(share, c.n, name, s, kept, metrics.megabytes_per_second(c, s), s / got["doubling"][0]) for name, (s, kept) in got.items()]
        return spark.createDataFrame(rows, "share int, n long, method string, seconds double, within_limit boolean, megabytes_per_second double, doubling_speed_up double")

    return run


def _costs(spark: SparkSession, d: str) -> DataFrame:
    """Shuffle, spill and CPU of the methods on a prefix of the nucleotides."""
    c = _prefix(w.dna)(spark, d)
    names = ("shuffle_written", "shuffle_read", "memory_spilled", "disk_spilled", "cpu_ns")
    own = {name: metrics.stage_costs(spark, lambda make=make: make(c)) for name, make in {"bucketed_merge": lambda c: bucketed.build(c, kernel="merge"), "hybrid": lambda c: hybrid.build(c).ranks}.items()}
    return spark.createDataFrame([(name, c.n, *(int(x[k]) for k in names)) for name, x in own.items()], "method string, n long, " + ", ".join(f"{k} long" for k in names))


def _scale_out(spark: SparkSession, d: str) -> DataFrame:
    """Speed-up of the merge kernel with more buckets, hence cores."""
    c = _prefix(w.dna)(spark, d)
    return spark.createDataFrame([(k, x) for k, x in metrics.scale_out(lambda r: bucketed.build(c, kernel="merge", r=r), (1, 2, 4)).items()], "buckets int, speed_up double")


def _sorts() -> dict[str, dict[str, str]]:
    """The options of the bucketed sorts, by name."""
    out: dict[str, dict[str, str]] = {}
    for kernel in partial.KERNELS:
        out[kernel] = {"kernel": kernel}
        out[f"{kernel}_chunk_join"] = {"kernel": kernel, "reader": "chunk_join"}
    for splitters in ("histogram", "orderby"):
        out[splitters] = {"splitters": splitters}
    return out | {"span_direct": {"kernel": "merge", "reduction": "span_direct"}}


def _variants() -> dict[str, Callable[[corpus.Corpus], DataFrame]]:
    """All ways to a suffix array, by name: (rank, pos) of a text."""
    sorted_ = lambda **options: lambda c: bucketed.build(c, **options).select("rank", "pos")
    doubled = lambda **options: lambda c: suffix_array.invert(doubling.build(c, **options).ranks)
    out = {"mapreduce_basic": naive.mapreduce_sort, "hybrid": lambda c: suffix_array.invert(hybrid.build(c).ranks)}
    out |= {name: sorted_(**options) for name, options in _sorts().items()}
    for pairing in ("join", "union_reduce", "block"):
        for rerank in doubling.RERANKS:
            out[f"doubling_{pairing}_{rerank}"] = doubled(pairing=pairing, rerank=rerank, active_only=False)
    out["doubling_active_set"] = doubled(active_only=True)
    out["doubling_literal_rounds"] = doubled(h0=1, rounds="paper", active_only=False)
    out["doubling_published"] = lambda c: suffix_array.invert(_published(c).ranks)
    return out


#: Variants that run over whole texts, besides the refining kernel (on all three) and the hybrid; the others run over a prefix of the nucleotides.
WHOLE = {"dna": ("merge", "histogram", "orderby", "refine_chunk_join", "hybrid"), "english": ("refine_chunk_join", "hybrid"), "proteins": ("merge", "hybrid")}


def _inverted(text: Callable) -> Query:
    """The text against the inverse of its transform: (n, rows, wrong)."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        c = text(spark, d)
        got = bwt.invert(bwt.from_suffix_array(bucketed.build(c).select("rank", "pos"), c), c).select("pos", F.col("code").alias("got"))
        both = corpus.text(c).join(got, "pos", "full")
        return both.agg(F.lit(c.n).cast("long").alias("n"), F.count("got").alias("rows"), F.count_if(~F.col("code").eqNullSafe(F.col("got"))).alias("wrong"))

    return run


def _entropy(spark: SparkSession, d: str) -> DataFrame:
    """Order-0 entropy of the text, and of the move-to-front codes of its transform."""
    c = w.english(spark, d)
    t = bucketed.transform(c)
    return compress.entropy(t, "code").withColumn("of", F.lit("text")).unionByName(compress.entropy(compress.mtf(t, c.sigma), "mtf").withColumn("of", F.lit("transform")))


def _bigram_distance(spark: SparkSession, d: str) -> DataFrame:
    rows = w.items_rows(spark, d)
    pairs = rows.select(F.col("item_id").alias("a"), (F.col("item_id") + 1).alias("b"))
    return features.distance(features.bwt_bigrams(rows, "item_id", "text"), "item_id", pairs).withColumn("distance", F.round("distance", 6))


def _all_bigram_distances(spark: SparkSession, d: str) -> DataFrame:
    """Between all pairs of items."""
    rows = w.items_rows(spark, d)
    ids = rows.select("item_id").distinct()
    pairs = ids.select(F.col("item_id").alias("a")).join(ids.select(F.col("item_id").alias("b")), F.col("a") < F.col("b"))
    return features.distance(features.bwt_bigrams(rows, "item_id", "text"), "item_id", cut(pairs))


def _scale_report(spark: SparkSession, d: str) -> DataFrame:
    """Prefixes of the nucleotide text: rounds, and what is left unresolved after each."""
    whole, out = w.dna(spark, d), None
    for part in (4, 2, 1):
        c = corpus.prefix_of(whole, whole.n // part)
        rows = doubling.rounds_table(spark, hybrid.build(c)).select(F.lit(1 / part).alias("share"), F.lit(c.n).cast("long").alias("n"), "round", "reach", "unresolved")
        out = rows if out is None else out.unionByName(rows)
    return out


def _splits(spark: SparkSession, d: str) -> DataFrame:
    return naive.split_index(w.items_rows(spark, d), "item_id", "text", 4).select("split", "n", "primary")


def _stream(spark: SparkSession, d: str) -> DataFrame:
    out = live.run_to_table(live.symbol_counts(live.read_events(spark, f"{d}/events.parquet")))
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "symbol", "cnt")


def _docs(spark: SparkSession, d: str) -> DataFrame:
    return spark.read.parquet(f"{d}/documents.parquet")


def _cube(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).cube("lang", "source").agg(F.sum(F.char_length("text")).alias("symbols"), F.count(F.lit(1)).alias("docs"), F.grouping_id().alias("level"))


def _clean_docs(spark: SparkSession, d: str) -> DataFrame:
    labels = spark.read.parquet(f"{d}/labels.parquet").where("quality = 1 and toxic = 0")
    return _docs(spark, d).join(labels, "doc_id", "left_semi").groupBy("lang").agg(F.count(F.lit(1)).alias("docs"), F.sum(F.char_length("text")).alias("symbols"))


def _unlabelled(spark: SparkSession, d: str) -> DataFrame:
    return _docs(spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id", "left_anti").select("doc_id", "n_chars")


def _words_only_in(spark: SparkSession, d: str) -> DataFrame:
    """Six-letter words of the benchmark that no English document has as a word."""
    own = w.english_rows(spark, d).select(F.explode(F.split("text", r"[^A-Za-z]+")).alias("word")).where("char_length(word) = 6").distinct()
    return _six(spark, d).exceptAll(own).select("word")


def _top_words(spark: SparkSession, d: str) -> DataFrame:
    """The ten most frequent 4-mers of the nucleotide text, ties by the word."""
    return _kmer_histogram(spark, d).orderBy(F.desc("cnt"), "word").limit(10)


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {
        "golden_examples": _golden,
        "symbol_counts_smaller": _symbol_counts,
        "kmer_histogram": _kmer_histogram,
        "kmer_positions": _kmer_positions,
        "kmer_hash_lookup": _kmer_lookup,
        "bucket_property": _property,
        "bucket_lmax": _gaps,
        "bucket_block_costs": lambda spark, d: metrics.block_costs(w.items(spark, d), 3, 16).withColumn("touched", F.col("touched").cast("long")),
        "bucket_balance": lambda spark, d: metrics.balance(bucketed.partition(w.dna(spark, d), 8, 16)),
        "sa_naive": lambda spark, d: naive.suffix_array(w.items_rows(spark, d), "item_id", "text"),
        "bwt_rotations": lambda spark, d: naive.rotations_bwt(w.items_rows(spark, d), "item_id", "text"),
        "sa_mapreduce_basic": lambda spark, d: naive.mapreduce_sort(w.items(spark, d)),
        "sa_split_input": _splits,
        "sa_hybrid": lambda spark, d: suffix_array.invert(hybrid.build(w.items(spark, d)).ranks),
        "isa_init": _rounds_of_items(0),
        "isa_round1": _rounds_of_items(1),
        "isa_round2": _rounds_of_items(2),
        "isa_doubling_literal_rounds": _doubled_items(h0=1, rounds="paper", active_only=False),
        "bwt_from_sa": _bwt_from_sa,
        "primary_index": _primary,
        "bwt_inverse_roundtrip": _inverse,
        "bwt_per_item": lambda spark, d: bwt.per_row(w.items_rows(spark, d), "item_id", "text"),
        "bwt_per_item_relational": lambda spark, d: bwt.per_row_relational(w.items_rows(spark, d), "item_id", "text"),
        "bwt_per_document": lambda spark, d: bwt.per_row(_docs(spark, d), "doc_id", "text"),
        "pages_bwt": lambda spark, d: bwt.per_row(spark.read.parquet(f"{d}/pages.parquet"), "page_id", "html").select("page_id", F.sha2("bwt", 256).alias("bwt_sha256"), "primary"),
        "bwt_runs": _runs,
        "bwt_mtf_entropy": _entropy,
        "bwt_bigrams": lambda spark, d: features.bwt_bigrams(w.items_rows(spark, d), "item_id", "text"),
        "bwt_bigram_distance": _bigram_distance,
        "fm_count": _fm_count,
        "fm_count_joined": _fm_count_joined,
        "fm_locate": _fm_locate,
        "fm_count_approx": _approx,
        "sa_search": _sa_search,
        "sa_search_passages": _sa_search_passages,
        "sa_search_patterns": _counted(_english_index, lambda c, _, built, p: suffix_array.binary_search(built.select("rank", "pos"), c, p)),
        "kmer_lookup_words": lambda spark, d: kmers.lookup_any(w.english(spark, d), _patterns(spark, d, passages=False).select(F.col("pattern").alias("word"))),
        "fm_count_patterns": _counted(_english_index, lambda c, index, _, p: fm.count(index, p)),
        "fm_count_joined_patterns": _counted(_english_index, lambda c, index, _, p: fm.count_joined(index, p)),
        "fm_count_approx_patterns": _counted(_english_index, lambda c, index, _, p: fm.count_approx(index, p, 1)),
        "bwt_bigram_distance_all": _all_bigram_distances,
        "lcp_items": _lcp,
        "longest_repeat": _longest,
        "longest_repeat_items": _longest_items,
        "bwt_mtf_entropy_items": _items_entropy,
        "seq_events_bwt": lambda spark, d: bwt.per_row(w.event_sequences(spark, d), "user_id", "text"),
        "lineitem_flags_bwt": lambda spark, d: bwt.per_row(w.line_flags(spark, d), "l_suppkey", "text"),
        "conv_bwt": lambda spark, d: bwt.per_row(w.chats(spark, d), "conv_id", "text"),
        "part_names_bwt": lambda spark, d: bwt.per_row(spark.read.parquet(f"{d}/part.parquet").select("p_partkey", w.without_terminator("p_name").alias("text")), "p_partkey", "text"),
        "iid_dna_sa": lambda spark, d: bucketed.build(w.random_bases(spark, d), kernel="radix").select("rank", "pos"),
        "check_english_refine": _checked_in_turns(w.english),
        "check_dna_refine": _checked_in_turns(w.dna, k=12),
        "check_proteins_refine": _checked_in_turns(w.proteins),
        "check_english_hybrid": _checked((w.english, lambda c: suffix_array.invert(hybrid.build(c).ranks))),
        "scale_dna_rounds": _scale_report,
        "stream_symbol_counts": _stream,
        "symbols_cube": _cube,
        "clean_documents": _clean_docs,
        "unlabelled_documents": _unlabelled,
        "benchmark_only_words": _words_only_in,
        "top_kmers": _top_words,
    }
    for kernel in partial.KERNELS:
        out[f"sa_bucketed_{kernel}"] = _sorted_items(k=4, kernel=kernel)
        out[f"sa_bucketed_{kernel}_chunk_join"] = _sorted_items(k=4, r=8, kernel=kernel, reader="chunk_join")
    for splitters in ("histogram", "orderby"):
        out[f"sa_bucketed_{splitters}"] = _sorted_items(k=4, splitters=splitters)
    out["sa_bucketed_span_direct"] = _sorted_items(k=4, kernel="merge", reduction="span_direct")
    for pairing in ("join", "union_reduce", "block"):
        for rerank in doubling.RERANKS:
            out[f"isa_doubling_{pairing}_{rerank}"] = _doubled_items(pairing=pairing, rerank=rerank, active_only=False)
    out["isa_doubling_active_set"] = _doubled_items(active_only=True)
    for name, text in (("english", w.english), ("dna", w.dna), ("proteins", w.proteins)):
        for variant in WHOLE[name]:
            out[f"check_{name}_{variant}"] = _checked_in_turns(text, **_sorts()[variant]) if variant in _sorts() else _checked((text, _variants()[variant]))
        out[f"check_{name}_inverse"] = _inverted(text)
    for variant, make in _variants().items():
        if f"check_dna_{variant}" not in out:
            out[f"check_dna_part_{variant}"] = _checked((_prefix(w.dna), make))
    out["isa_doubling_published"] = lambda spark, d: _published(w.items(spark, d)).ranks
    out["sa_bucketed_suggested_k"] = _sorted_items(k="suggested")
    out["table_dna"], out["table_proteins"] = _table(w.dna), _table(w.proteins)
    out["stage_costs_dna"], out["scale_out_dna"] = _costs, _scale_out
    return out


_ITEMS = "t AS (SELECT string_agg(replace(text, '$', ''), chr(10) ORDER BY item_id, replace(text, '$', '')) AS s FROM benchmark WHERE text IS NOT NULL)"
_ITEM_SUFFIXES = f"{_ITEMS}, p AS (SELECT s, unnest(range(0, length(s) + 1)) AS pos FROM t), x AS (SELECT pos, substr(s, pos + 1) AS suffix, CASE WHEN pos = 0 THEN '$' ELSE substr(s, pos, 1) END AS before FROM p)"
_ITEM_RANKS = f"WITH {_ITEM_SUFFIXES}, r AS (SELECT pos, before, suffix, row_number() OVER (ORDER BY suffix) - 1 AS rank FROM x)"
_SA = f"{_ITEM_RANKS} SELECT rank, pos FROM r"
_ISA = f"{_ITEM_RANKS} SELECT pos, rank AS rnk FROM r"


def _prefix_ranks(k: int) -> str:
    return f"WITH {_ITEM_SUFFIXES} SELECT pos, rank() OVER (ORDER BY substr(suffix, 1, {k})) - 1 AS rnk FROM x"


def _rows_bwt(source: str, key: str) -> str:
    """source: SQL of (key, s); texts are sorted suffix by suffix."""
    return f"""
WITH t AS ({source}), p AS (SELECT {key}, s, unnest(range(0, length(s) + 1)) AS pos FROM t WHERE s IS NOT NULL),
r AS (SELECT {key}, pos, CASE WHEN pos = 0 THEN '$' ELSE substr(s, pos, 1) END AS before, row_number() OVER (PARTITION BY {key} ORDER BY substr(s, pos + 1)) - 1 AS rank FROM p)
SELECT {key}, string_agg(before, '' ORDER BY rank) AS bwt, max(CASE WHEN pos = 0 THEN rank END) AS "primary" FROM r GROUP BY {key}
"""


_ITEM_ROWS = "SELECT item_id, replace(text, '$', '') AS s FROM benchmark"
_ENGLISH = "e AS (SELECT string_agg(replace(text, '$', ''), chr(10) ORDER BY doc_id) AS s FROM documents WHERE lang = 'en' AND text IS NOT NULL), c AS (SELECT unnest(string_split(s, '')) AS ch, generate_subscripts(string_split(s, ''), 1) - 1 AS pos FROM e)"
_LETTERS = "abcdefghijklmnopqrstuvwxyz"


def _mapped(alphabet: str) -> str:
    to = (alphabet * 26)[:26]
    return f"e AS (SELECT string_agg(translate(regexp_replace(lower(text), '[^a-z]', '', 'g'), '{_LETTERS}', '{to}'), chr(10) ORDER BY doc_id) AS s FROM documents WHERE text IS NOT NULL)"


_SIX = "(SELECT DISTINCT word FROM (SELECT unnest(regexp_split_to_array(replace(text, '$', ''), '[^A-Za-z]+')) AS word FROM benchmark) WHERE length(word) = 6)"
_HISTOGRAM = f"""
WITH {_mapped(w.NUCLEOTIDES)}, c AS (SELECT unnest(string_split(s, '')) AS ch, generate_subscripts(string_split(s, ''), 1) AS pos FROM e UNION ALL SELECT '$', 1 + length(s) FROM e),
k AS (SELECT ch || lead(ch, 1, '$') OVER o || lead(ch, 2, '$') OVER o || lead(ch, 3, '$') OVER o AS word FROM c WINDOW o AS (ORDER BY pos))
SELECT word, count(*) AS cnt FROM k GROUP BY word
"""


def oracle_sql() -> dict[str, str]:
    n_of = lambda e: f"WITH {e} SELECT length(s) + 1 AS n, length(s) + 1 AS rows, length(s) + 1 AS positions, 0 AS misplaced, 0 AS violations FROM e"
    english = n_of(_ENGLISH.split(", c AS")[0])
    rotated = _rows_bwt(_ITEM_ROWS, "item_id")
    out = {
        "golden_examples": f"WITH t AS (SELECT row_number() OVER () AS i, item_id, s FROM ({_ITEM_ROWS}) WHERE s IS NOT NULL), o AS (SELECT * FROM (VALUES ('smallest', ''), ('largest', chr(1114111))) AS v(terminator, ending)), p AS (SELECT i, item_id, s, terminator, ending, unnest(range(0, length(s) + 1)) AS pos FROM t, o), r AS (SELECT i, item_id, terminator, pos, CASE WHEN pos = 0 THEN '$' ELSE substr(s, pos, 1) END AS before, row_number() OVER (PARTITION BY i, terminator ORDER BY substr(s, pos + 1) || ending) - 1 AS rank FROM p) SELECT item_id, terminator, string_agg(pos::VARCHAR, ' ' ORDER BY rank) AS sa, string_agg(before, '' ORDER BY rank) AS bwt, max(CASE WHEN pos = 0 THEN rank END) AS \"primary\" FROM r GROUP BY i, item_id, terminator",
        "symbol_counts_smaller": f"WITH {_ENGLISH}, g AS (SELECT ch AS symbol, count(*) AS cnt, ord(ch) AS o FROM c GROUP BY ch UNION ALL SELECT '$', 1, -1) SELECT symbol, cnt, coalesce(sum(cnt) OVER (ORDER BY o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS smaller FROM g",
        "kmer_histogram": _HISTOGRAM,
        "top_kmers": f"{_HISTOGRAM} ORDER BY cnt DESC, word LIMIT 10",
        "kmer_positions": f"WITH {_ITEM_SUFFIXES} SELECT pos, rpad(substr(suffix, 1, 5), 5, '$') AS word FROM x",
        "kmer_hash_lookup": f"WITH {_ENGLISH}, k AS (SELECT pos, ch || lead(ch, 1, '') OVER o || lead(ch, 2, '') OVER o || lead(ch, 3, '') OVER o || lead(ch, 4, '') OVER o || lead(ch, 5, '') OVER o AS word FROM c WINDOW o AS (ORDER BY pos)) SELECT word, pos FROM k WHERE word IN {_SIX}",
        "bucket_property": f"WITH {_mapped(w.NUCLEOTIDES)} SELECT true AS apart, length(s) + 1 AS members FROM e",
        "bucket_lmax": f"WITH {_ENGLISH}, a AS (SELECT ch AS symbol, pos FROM c UNION ALL SELECT '$', max(pos) + 1 FROM c), g AS (SELECT symbol, lead(pos, 1, (SELECT max(pos) + 1 FROM a)) OVER (PARTITION BY symbol ORDER BY pos) - pos AS gap FROM a) SELECT symbol, count(*) AS members, max(gap)::BIGINT AS l_max FROM g GROUP BY symbol",
        "sa_naive": f"WITH t AS ({_ITEM_ROWS}), p AS (SELECT item_id, s, unnest(range(0, length(s) + 1)) AS pos FROM t) SELECT item_id, row_number() OVER (PARTITION BY item_id ORDER BY substr(s, pos + 1)) - 1 AS rank, pos FROM p",
        "bwt_rotations": rotated,
        "bwt_per_item": rotated,
        "bwt_per_item_relational": rotated,
        "isa_init": _prefix_ranks(1),
        "isa_round1": _prefix_ranks(2),
        "isa_round2": _prefix_ranks(4),
        "bwt_from_sa": f"{_ITEM_RANKS} SELECT rank, before AS symbol FROM r",
        "primary_index": f'{_ITEM_RANKS} SELECT rank AS "primary" FROM r WHERE pos = 0',
        "bwt_inverse_roundtrip": f"WITH {_ITEMS} SELECT pos, CASE WHEN pos = length(s) THEN '$' ELSE substr(s, pos + 1, 1) END AS symbol FROM (SELECT s, unnest(range(0, length(s) + 1)) AS pos FROM t)",
        "bwt_runs": f"{_ITEM_RANKS}, a AS (SELECT rank, before, CASE WHEN before = lag(before) OVER (ORDER BY rank) THEN 0 ELSE 1 END AS new FROM r), b AS (SELECT rank, before, sum(new) OVER (ORDER BY rank) - 1 AS run FROM a) SELECT run::BIGINT AS run, min(before) AS symbol, min(rank) AS start, count(*) AS len FROM b GROUP BY run",
        "bwt_bigrams": f"WITH b AS ({rotated}), i AS (SELECT item_id, bwt, unnest(range(1, length(bwt))) AS i FROM b) SELECT item_id, substr(bwt, i, 1) AS first, substr(bwt, i + 1, 1) AS second, count(*) AS cnt FROM i GROUP BY ALL",
        "fm_count": "WITH p AS (SELECT item_id, replace(text, '$', '') AS w FROM benchmark), d AS (SELECT replace(text, '$', '') AS s FROM documents WHERE lang = 'en') SELECT item_id AS pattern_id, coalesce(sum((length(s) - length(replace(s, w, ''))) // length(w)), 0)::BIGINT AS cnt FROM p, d GROUP BY item_id",
        "fm_locate": "WITH p AS (SELECT item_id, replace(text, '$', '') AS w FROM benchmark), d AS (SELECT doc_id, replace(text, '$', '') AS s FROM documents WHERE lang = 'en'), h AS (SELECT item_id, doc_id, w, string_split(s, w) AS parts FROM p, d WHERE contains(s, w)), q AS (SELECT item_id, doc_id, length(w) AS m, unnest(range(1, len(parts))) AS i, parts FROM h) SELECT item_id AS pattern_id, doc_id, (list_sum(list_transform(parts[1:i], lambda x: length(x))) + (i - 1) * m)::BIGINT AS \"offset\" FROM q",
        "fm_count_joined": f"WITH {_ENGLISH}, k AS (SELECT ch || lead(ch, 1, '') OVER o || lead(ch, 2, '') OVER o || lead(ch, 3, '') OVER o || lead(ch, 4, '') OVER o || lead(ch, 5, '') OVER o AS word FROM c WINDOW o AS (ORDER BY pos)) SELECT v.word, count(k.word) AS cnt FROM {_SIX} v LEFT JOIN k USING (word) GROUP BY v.word",
        "sa_search": f"WITH {_ITEM_SUFFIXES} SELECT v.word, count(*) AS cnt FROM {_SIX} v JOIN x ON substr(x.suffix, 1, 6) = v.word GROUP BY v.word",
        "fm_count_approx": f"WITH {_ITEM_SUFFIXES}, k AS (SELECT substr(suffix, 1, 6) AS q, count(*) AS c FROM x WHERE length(suffix) >= 6 GROUP BY q), m AS (SELECT v.word, k.c, len(list_filter(range(1, 7), lambda i: substr(v.word, i, 1) <> substr(k.q, i, 1))) AS mismatches FROM {_SIX} v, k) SELECT word, mismatches::INTEGER AS mismatches, sum(c)::BIGINT AS cnt FROM m WHERE mismatches <= 1 GROUP BY ALL",
        "seq_events_bwt": _rows_bwt("SELECT user_id, string_agg(substr(event_type, 1, 1), '' ORDER BY ts, event_id) AS s FROM events GROUP BY user_id", "user_id"),
        "lineitem_flags_bwt": _rows_bwt("SELECT l_suppkey, string_agg(l_returnflag || l_linestatus, '' ORDER BY l_orderkey, l_linenumber, l_partkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS s FROM lineitem GROUP BY l_suppkey", "l_suppkey"),
        "conv_bwt": _rows_bwt("SELECT conv_id, string_agg(replace(text, '$', ''), chr(10) ORDER BY turn, role, replace(text, '$', '')) AS s FROM conversations GROUP BY conv_id", "conv_id"),
        "part_names_bwt": _rows_bwt("SELECT p_partkey, replace(p_name, '$', '') AS s FROM part", "p_partkey"),
        "iid_dna_sa": "WITH t AS (SELECT string_agg(array_to_string(list_transform(range(0, len(embedding) // 2), lambda i: substr('ACGT', 1 + CASE WHEN embedding[2 * i + 1] >= 0 THEN 2 ELSE 0 END + CASE WHEN embedding[2 * i + 2] >= 0 THEN 1 ELSE 0 END, 1)), ''), '' ORDER BY vec_id) AS s FROM embeddings), p AS (SELECT s, unnest(range(0, length(s) + 1)) AS pos FROM t) SELECT row_number() OVER (ORDER BY substr(s, pos + 1)) - 1 AS rank, pos FROM p",
        "check_english_refine": english,
        "check_english_hybrid": english,
        "check_dna_refine": n_of(_mapped(w.NUCLEOTIDES)),
        "check_proteins_refine": n_of(_mapped(w.AMINO_ACIDS)),
        "stream_symbol_counts": "SELECT strftime(ts, '%Y-%m-%d') AS day, substr(event_type, 1, 1) AS symbol, count(*) AS cnt FROM events GROUP BY ALL",
        "symbols_cube": "SELECT lang, source, sum(length(text))::BIGINT AS symbols, count(*) AS docs, grouping(lang, source)::BIGINT AS level FROM documents GROUP BY CUBE (lang, source)",
        "clean_documents": "SELECT lang, count(*) AS docs, sum(length(text))::BIGINT AS symbols FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0) GROUP BY lang",
        "unlabelled_documents": "SELECT doc_id, n_chars FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)",
        "benchmark_only_words": f"SELECT word FROM {_SIX} WHERE word NOT IN (SELECT unnest(regexp_split_to_array(replace(text, '$', ''), '[^A-Za-z]+')) FROM documents WHERE lang = 'en')",
    }
    out["sa_search_passages"] = out["fm_count"]
    steps = [f"l{i + 1} AS (SELECT rank, pos, suffix, above, lcp + CASE WHEN substr(suffix, (lcp + 1)::INTEGER, {1 << 16 - i}) = substr(above, (lcp + 1)::INTEGER, {1 << 16 - i}) AND length(above) >= lcp + {1 << 16 - i} THEN {1 << 16 - i} ELSE 0 END AS lcp FROM l{i})" for i in range(17)]
    passages = f"WITH {_ITEM_SUFFIXES}, r AS (SELECT suffix, pos, row_number() OVER (ORDER BY suffix) - 1 AS rank FROM x), l0 AS (SELECT rank, pos, suffix, lag(suffix) OVER (ORDER BY rank) AS above, 0::BIGINT AS lcp FROM r), {', '.join(steps)}, l AS (SELECT * FROM l17)"
    out["lcp_items"] = f"{passages} SELECT rank, pos, lcp FROM l"
    out["longest_repeat_items"] = f"{passages} SELECT max(lcp) AS longest_repeat, (sum(length(suffix) - lcp))::BIGINT AS distinct_substrings FROM l"
    out["bwt_mtf_entropy_items"] = f"{_ITEM_RANKS}, g AS (SELECT before, count(*)::DOUBLE AS c FROM r GROUP BY before), a AS (SELECT rank, before, lag(before) OVER (ORDER BY rank) AS prior FROM r) SELECT (SELECT sum(c) FROM g)::BIGINT AS n, round((SELECT log2(sum(c)) - sum(c * log2(c)) / sum(c) FROM g), 6) AS bits, count(*) FILTER (WHERE prior IS NULL OR prior <> before) AS runs FROM a"
    splits = f"SELECT split, length(s) + 1 AS n, s FROM (SELECT (item_id % 4)::INTEGER AS split, string_agg(replace(text, '$', ''), chr(10) ORDER BY item_id) AS s FROM benchmark WHERE text IS NOT NULL GROUP BY split)"
    out["sa_split_input"] = f"WITH t AS ({splits}), p AS (SELECT split, n, s, unnest(range(0, n)) AS pos FROM t), r AS (SELECT split, n, pos, row_number() OVER (PARTITION BY split ORDER BY substr(s, pos + 1)) - 1 AS rank FROM p) SELECT split, n, rank AS \"primary\" FROM r WHERE pos = 0"
    out["bucket_block_costs"] = f"WITH {_ITEM_SUFFIXES}, m AS (SELECT pos, rpad(substr(suffix, 1, 3), 3, chr(1)) AS w, count(*) OVER () AS n FROM x), h AS (SELECT w, count(*) AS c FROM m GROUP BY w), b AS (SELECT w, coalesce(sum(c) OVER (ORDER BY w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM h), k AS (SELECT (before * 16 // n)::INTEGER AS bucket, pos, n FROM m JOIN b USING (w)), g AS (SELECT bucket, lead(pos, 1, n) OVER (PARTITION BY bucket ORDER BY pos) - pos AS gap FROM k) SELECT bucket, count(*) AS members, max(gap)::BIGINT AS l_max, (count(*) * (max(gap) + 2))::BIGINT AS touched FROM g GROUP BY bucket"
    out["bwt_bigram_distance"] = f"WITH b AS ({rotated}), i AS (SELECT item_id, bwt, unnest(range(1, length(bwt))) AS i FROM b), c AS (SELECT item_id, substr(bwt, i, 2) AS pair, count(*) AS cnt FROM i GROUP BY ALL), s AS (SELECT item_id, pair, cnt / sum(cnt) OVER (PARTITION BY item_id) AS p FROM c), e AS (SELECT item_id AS a, item_id + 1 AS b, pair, p AS x, 0.0 AS y FROM s UNION ALL SELECT item_id - 1, item_id, pair, 0.0, p FROM s), f AS (SELECT a, b, pair, sum(x) AS x, sum(y) AS y FROM e GROUP BY ALL) SELECT a, b, round(sum(abs(x - y)) / 2, 6) AS distance FROM f WHERE a IN (SELECT item_id FROM benchmark) GROUP BY a, b"
    whole = {"english": english, "dna": n_of(_mapped(w.NUCLEOTIDES)), "proteins": n_of(_mapped(w.AMINO_ACIDS))}
    for name, sql in whole.items():
        for variant in WHOLE[name]:
            out[f"check_{name}_{variant}"] = sql
    part = f"WITH {_mapped(w.NUCLEOTIDES)}, l AS (SELECT (length(s) + 1) // {PART} + 1 AS n FROM e) SELECT n, n AS rows, n AS positions, 0 AS misplaced, 0 AS violations FROM l"
    for name, e in (("english", _ENGLISH.split(", c AS")[0]), ("dna", _mapped(w.NUCLEOTIDES)), ("proteins", _mapped(w.AMINO_ACIDS))):
        out[f"check_{name}_inverse"] = f"WITH {e} SELECT length(s) + 1 AS n, length(s) + 1 AS rows, 0 AS wrong FROM e"
    for name in queries():
        if name.startswith(("sa_bucketed_", "sa_mapreduce", "sa_hybrid")):
            out[name] = _SA
        elif name.startswith("isa_doubling_"):
            out[name] = _ISA
        elif name.startswith("check_dna_part_"):
            out[name] = part
    return out


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The transform of all English documents as one text: (rank, symbol)."""
    c = w.english(spark, sf_dir)
    return bwt.symbols(bucketed.build(c).select("rank", "code"), c)
