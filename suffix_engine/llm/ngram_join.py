"""N-gram Jaccard join: candidate groups by rare shingles, T-occurrence search with divided lists inside them."""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.llm.blocks import NO_ID, Docs, Items, Kernel, chained, exchange, mix, range_hashes
from suffix_engine.llm.graph import connected
from suffix_engine.llm.lines import _LOWER
from suffix_engine.llm.windows import word_ranges
from suffix_engine.session import cut, written

#: Documents that a task searches at once; larger candidate groups are cut into blocks of about that size.
GROUP = 512
#: By what share the sizes of sets differ at most in a block of a list or a group that is cut.
CLASS = 0.02
#: Weight of a list's length in the choice of how many lists are probed instead of merged.
PROBE_WEIGHT = 0.0085


def needed(percent: int, size):
    """Least overlap that a set of that size has with one it links with."""
    return -(-percent * size // 100)


def both_needed(percent: int, a, b):
    """Least overlap of two sets of these sizes that link."""
    return -(-percent * (a + b) // (100 + percent))


def reach(percent: int, size, shared):
    """Greatest size of a set that one of this size links with, when only so many of its shingles are in others, too."""
    return (100 + percent) * shared // percent - size


_LOW = np.uint64(0xFFFFFFFF)


@dataclass
class ShingleKernel(Kernel):
    """Distinct shingles of each document; how many sets hold each one is summed up in the buckets.

    A bucket sees 32 bits of a shingle and answers with the magnitude of its count (0: no other set holds it). That is a function of the
    shingle, so (magnitude, hash) is one order for all documents, rare shingles first, whatever shingles share their 32 bits.
    """

    size: int = 4
    percent: int = 85
    schema = "doc_id long, n_shingles long, one long, two long, prefix array<bigint>, tokens binary"

    def _sets(self, docs: Docs):
        """Per document the size and a digest of its set; the distinct shingles of the first document of each set, and their bounds."""
        low = _LOWER[docs.bytes]
        begin, end, first = word_ranges(low, docs.bounds)
        word = range_hashes(low, begin, end)
        counts = np.diff(first)
        shingle = chained(word, self.size)
        n = np.maximum(counts - self.size + 1, 0)
        doc = np.repeat(np.arange(len(docs)), n)
        at = np.repeat(first[:-1] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
        token = shingle[at] if len(at) else np.zeros(0, np.uint64)
        short = np.flatnonzero((counts > 0) & (counts < self.size))
        whole = [mix(chained(word[first[i] : first[i + 1]], int(counts[i])) + np.uint64(counts[i]))[0] for i in short]
        doc, token = np.r_[doc, short], np.r_[token, np.array(whole, np.uint64)]
        order = np.lexsort((token, doc))
        doc, token = doc[order], token[order]
        new = np.r_[True, (doc[1:] != doc[:-1]) | (token[1:] != token[:-1])] if len(doc) else np.zeros(0, bool)
        doc, token = doc[new], token[new]
        size = np.bincount(doc, minlength=len(docs))
        edge = np.r_[0, np.cumsum(size)]
        digest, seen = np.zeros((len(docs), 2), np.uint64), set()
        leads = np.zeros(len(docs), bool)
        for i in np.flatnonzero(size).tolist():
            own = hashlib.blake2b(token[edge[i] : edge[i + 1]], digest_size=16).digest()
            digest[i] = np.frombuffer(own, np.uint64)
            leads[i] = own not in seen
            seen.add(own)
        return size, digest, leads, token[leads[doc]], np.r_[0, np.cumsum(size[leads])]

    def items(self, docs, n_buckets):
        size, digest, leads, token, edge = self._sets(docs)
        key = ((token >> np.uint64(32)) % np.uint64(n_buckets)) << np.uint64(32) | (token & _LOW)
        own, item, count = np.unique(key, return_inverse=True, return_counts=True)
        columns = [(own & _LOW).astype(np.uint32), count.astype(np.uint32)]
        return Items((own >> np.uint64(32)).astype(np.int64), columns, np.zeros(len(own), np.int64), np.zeros(0, np.uint8)), (size, digest, leads, token, edge, item)

    def resolve(self, items):
        own, item = np.unique(items.columns[0], return_inverse=True)
        total = np.bincount(item, weights=items.columns[1], minlength=len(own))
        return np.where(total > 1, np.floor(np.log2(np.maximum(total, 1))), 0).astype(np.uint8)[item]

    def apply(self, docs, items, known, answers):
        size, digest, leads, token, edge, item = known
        magnitude = answers[item]
        prefix, tokens = [None] * len(docs), [None] * len(docs)
        for row, i, j in zip(np.flatnonzero(leads), edge[:-1], edge[1:], strict=True):
            shared = magnitude[i:j] > 0
            n = int(shared.sum()) - needed(self.percent, int(j - i)) + 1
            if n > 0:
                t = token[i:j][shared]
                t = t[np.lexsort((t, magnitude[i:j][shared]))].view(np.int64)
                prefix[row], tokens[row] = t[:n], t.tobytes()
        return {
            "n_shingles": pa.array(size, pa.int64()),
            "one": pa.array(digest[:, 0].view(np.int64)),
            "two": pa.array(digest[:, 1].view(np.int64)),
            "prefix": pa.array(prefix, pa.list_(pa.int64())),
            "tokens": pa.array(tokens, pa.binary()),
        }


class Lists:
    """Inverted lists over a group of sets, and the search for sets with at least a needed overlap."""

    def __init__(self, tokens: list[np.ndarray]):
        self.n = len(tokens)
        self.lengths = np.array([len(t) for t in tokens], np.int64)
        flat = np.concatenate(tokens) if tokens else np.zeros(0, np.int64)
        owner = np.repeat(np.arange(self.n), [len(t) for t in tokens])
        _, number = np.unique(flat, return_inverse=True)
        self.of = np.split(number, np.cumsum([len(t) for t in tokens])[:-1])
        #: All postings, list after list, each in the order of the sets.
        self.postings = np.sort(number.astype(np.int64) * self.n + owner)
        self.edges = np.r_[0, np.cumsum(np.bincount(number))] if len(number) else np.zeros(1, np.int64)
        self.sets = self.postings % max(self.n, 1)

    def _merge(self, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The sets on the given short lists, and on how many each is."""
        n = last - first
        return np.unique(self.sets[np.repeat(first - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))], return_counts=True)

    def search(self, query: int, need: int, low: int, high: int, skip) -> Iterator[tuple[int, int]]:
        """(set, overlap) of the sets in [low, high) whose overlap with the query's is at least need; sets that skip(sets) marks are left out,
        and it is asked anew for each few candidates."""
        own = self.of[query]
        first = np.searchsorted(self.postings, own * self.n + low)
        last = np.searchsorted(self.postings, own * self.n + high)
        some = last > first
        own, first, last = own[some], first[some], last[some]
        if len(own) < need:
            return
        order = np.argsort(last - first, kind="stable")
        own, first, last = own[order], first[order], last[order]
        longest = int(last[-1] - first[-1])
        long = min(need - 1, int(need / (PROBE_WEIGHT * np.log2(longest + 1) + 1)))
        cut_ = len(own) - long
        found, counts = self._merge(first[:cut_], last[:cut_])
        keep = counts >= need - long
        found, counts = found[keep], counts[keep]
        order = np.argsort(-counts, kind="stable")
        found, counts = found[order], counts[order]
        while len(found):
            keep = ~skip(found)
            found, counts = found[keep], counts[keep]
            some, overlap = found[:8], counts[:8]
            found, counts = found[8:], counts[8:]
            if len(some) and long:
                wanted = own[cut_:, None] * self.n + some[None, :]
                at = np.searchsorted(self.postings, wanted)
                overlap = overlap + (self.postings[np.minimum(at, len(self.postings) - 1)] == wanted).sum(axis=0)
            for x, o in zip(some, overlap, strict=True):
                if o >= need:
                    yield int(x), int(o)


def _join(index: Lists, part: np.ndarray, query: int, size: np.ndarray, n_own: int, percent: int, skip: Callable) -> None:
    """Puts a query and those of the first n_own sets, which come by size, that it links with into one component; sets already there
    aren't compared again, nor those that the shingles which either shares with others can't reach."""
    own, most = int(size[query]), reach(percent, size, index.lengths)
    low, high = _window(size[:n_own], own, int(most[query]), percent)
    if low >= high:
        return
    far = most < own
    for x, overlap in index.search(query, int(both_needed(percent, own, int(size[low]))), low, high, lambda found: skip(found) | far[found] | (part[found] == part[query])):
        if part[x] != part[query] and overlap >= both_needed(percent, own, int(size[x])):
            part[part == part[query]] = part[x]


def _window(sizes: np.ndarray, size: int, most: int, percent: int) -> tuple[int, int]:
    """Which of the ascending sizes a set of that size and reach can link with."""
    return int(np.searchsorted(sizes, needed(percent, size))), int(np.searchsorted(sizes, min(100 * size // percent, most), side="right"))


def linked(tokens: list[np.ndarray], size: np.ndarray, hub: int, percent: int, hub_only: bool = False) -> np.ndarray:
    """Component numbers of the links between sets, which come by size.

    The hub is searched first. What hangs on it needs no comparing among itself; each of the rest is held against all of the hub's
    component and the rest before it. hub_only: only links with the hub are looked for.
    """
    index, part = Lists(tokens), np.arange(len(tokens))
    _join(index, part, hub, size, len(tokens), percent, lambda found: found == hub)
    for q in () if hub_only else np.flatnonzero(part != part[hub]).tolist():
        _join(index, part, q, size, len(tokens), percent, lambda found, q=q: (found >= q) & (part[found] != part[hub]))
    return part


def linked_with_probes(tokens: list[np.ndarray], size: np.ndarray, n_own: int, percent: int) -> np.ndarray:
    """Component numbers of the links between a probe and a set that is none; the first n_own sets are none, and come by size."""
    index, part = Lists(tokens), np.arange(len(tokens))
    for q in range(n_own, len(tokens)):
        _join(index, part, q, size, n_own, percent, lambda found: np.zeros(len(found), bool))
    return part


def _stars(rep: np.ndarray, part: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links of each set with the least id of its component."""
    least = np.full(len(rep), np.iinfo(np.int64).max)
    np.minimum.at(least, part, rep)
    least = least[part]
    return rep[least != rep], least[least != rep]


def _sets_of(table: pa.Table, *order: str) -> tuple[np.ndarray, np.ndarray, list[np.ndarray], np.ndarray]:
    rep, size = table["rep"].to_numpy(), table["n_shingles"].to_numpy()
    by = np.lexsort((rep, size, *(table[c].to_numpy(zero_copy_only=False) for c in order)))
    raw = table["tokens"]
    return rep[by], size[by], [np.frombuffer(raw[int(i)].as_py(), np.int64) for i in by], by


def _group_task(percent: int):
    """Links of a group as stars. Of cut groups only those with the hub, and (with v the hub) the loose sets that don't hang on it."""

    def run(table: pa.Table) -> pa.Table:
        rep, size, tokens, _ = _sets_of(table)
        hub, cut_ = table["hub"][0].as_py(), table["blocks"][0].as_py() > 1
        at = int(np.flatnonzero(rep == hub)[0])
        part = linked(tokens, size, at, percent, hub_only=cut_)
        u, v = _stars(rep, part)
        loose = rep[part != part[at]] if cut_ else rep[:0]
        return pa.table({"u": pa.array(np.r_[u, loose], pa.int64()), "v": pa.array(np.r_[v, np.full(len(loose), hub)], pa.int64()), "loose": pa.array(np.arange(len(u) + len(loose)) >= len(u), pa.bool_())})

    return run


def _list_task(percent: int):
    """Links between loose sets and the sets of one block of a list or of a group."""

    def run(table: pa.Table) -> pa.Table:
        rep, size, tokens, by = _sets_of(table, "probe")
        n_own = int((~table["probe"].to_numpy(zero_copy_only=False)).sum())
        part = linked_with_probes(tokens, size, n_own, percent)
        u, v = _stars(rep, part)
        return pa.table({"u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64())})

    return run


def group_links(sets: DataFrame, percent: int, group: int = GROUP) -> DataFrame:
    """(u, v): links between representatives, from rows (rep, n_shingles, prefix, tokens) with distinct sets.

    Two sets that link share a shingle of both prefixes, hence its list and the list's hub (least id). A hub's group, the union of its
    lists, is searched by one task if it is not over the given size. A larger one is cut into blocks, whose sets are held against the hub
    alone: what links with it needs no more comparing among itself. Each set left loose is held against the lists that brought it
    there, or against the group if it is no longer than these lists together (copies of one text share them all). Those over the size are
    cut into blocks by the size of their sets, and a set is only held against blocks that it can reach. Lists with equal sets are
    searched once.
    """
    listed = sets.select("rep", F.explode("prefix").alias("token"))
    sums = [F.bit_xor(F.xxhash64("rep", F.lit(seed))).alias(name) for seed, name in ((1, "_a"), (2, "_b"))]
    lists = listed.groupBy("token").agg(F.min("rep").alias("hub"), F.count(F.lit(1)).alias("n"), *sums).where("n > 1")
    lists = lists.groupBy("hub", "n", "_a", "_b").agg(F.min("token").alias("_token")).select("_token", "hub", "n")
    placed = cut(listed.join(lists, F.col("token") == F.col("_token")).select("token", "hub", "rep", "n"))
    member = placed.select("hub", "rep").distinct()
    sized = member.groupBy(F.col("hub").alias("_hub")).agg(F.count(F.lit(1)).alias("members"))
    dealt = member.join(sized, F.col("hub") == F.col("_hub")).select("hub", "rep", F.ceil(F.col("members") / group).cast("int").alias("blocks"))
    block = lambda n: F.pmod(F.xxhash64("rep"), n).cast("int")
    dealt = dealt.withColumn("block", F.explode(F.when(F.col("hub") == F.col("rep"), F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.array(block(F.col("blocks"))))))
    body = sets.select(F.col("rep").alias("_rep"), "n_shingles", "tokens")
    full = dealt.join(body, F.col("rep") == F.col("_rep")).drop("_rep")
    first = cut(full.groupBy("hub", "block").applyInArrow(_group_task(percent), "u long, v long, loose boolean"))
    links = first.where(~F.col("loose")).select("u", "v")
    loose = first.where("loose").select(F.col("v").alias("_hub"), F.col("u").alias("_loose")).distinct()
    # what each loose set is held against: lists by their token, or the group by its hub
    asks = placed.join(loose, (F.col("hub") == F.col("_hub")) & (F.col("rep") == F.col("_loose"))).groupBy("hub", "rep").agg(F.sum("n").alias("total"), F.collect_list("token").alias("lists"))
    asks = asks.join(sized, F.col("hub") == F.col("_hub")).withColumn("whole", F.col("members") <= F.col("total"))
    asks = cut(asks.select("rep", "whole", F.explode(F.when(F.col("whole"), F.array("hub")).otherwise(F.col("lists"))).alias("list")))
    facts = sets.select(F.col("rep").alias("_rep"), "n_shingles", F.expr(f"{100 + percent} * (octet_length(tokens) div 8) div {percent}").alias("_far")).withColumn("_far", F.col("_far") - F.col("n_shingles"))
    keys = ["whole", "list", "class", "block"]
    open_ = asks.select(F.col("whole").alias("_w"), F.col("list").alias("_l")).distinct()
    held = placed.select(F.lit(False).alias("whole"), F.col("token").alias("list"), "rep", "n").unionByName(member.join(sized, F.col("hub") == F.col("_hub")).select(F.lit(True).alias("whole"), F.col("hub").alias("list"), "rep", F.col("members").alias("n")))
    held = held.join(open_, (F.col("whole") == F.col("_w")) & (F.col("list") == F.col("_l")), "left_semi").join(facts, F.col("rep") == F.col("_rep"))
    held = cut(held.select("whole", "list", "rep", "n_shingles", "_far", F.when(F.col("n") > group, F.floor(F.log("n_shingles") / F.log(F.lit(1 + CLASS)))).otherwise(0).cast("long").alias("class")))
    classes = held.groupBy(F.col("whole").alias("_w"), F.col("list").alias("_l"), F.col("class").alias("_c")).agg(F.min("n_shingles").alias("_least"), F.max("n_shingles").alias("_most"), F.max("_far").alias("_farthest"), F.ceil(F.count(F.lit(1)) / group).cast("int").alias("blocks"))
    met = (F.col("whole") == F.col("_w")) & (F.col("list") == F.col("_l")) & (F.col("_least") <= F.col("_far")) & (100 * F.col("_most") >= percent * F.col("n_shingles")) & (F.col("_farthest") >= F.col("n_shingles"))
    asked = asks.join(facts, F.col("rep") == F.col("_rep")).join(classes, met)
    asked = cut(asked.select("whole", "list", F.col("_c").alias("class"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), "rep", F.lit(True).alias("probe")))
    dealt = held.join(classes, (F.col("whole") == F.col("_w")) & (F.col("list") == F.col("_l")) & (F.col("class") == F.col("_c"))).select("whole", "list", "class", block(F.col("blocks")).alias("block"), "rep", F.lit(False).alias("probe"))
    dealt = dealt.join(asked.select(*keys).distinct(), keys, "left_semi")
    second = dealt.unionByName(asked).join(body, F.col("rep") == F.col("_rep")).drop("_rep").groupBy(*keys).applyInArrow(_list_task(percent), "u long, v long")
    return links.unionByName(second)


def components(docs: DataFrame, size: int = 4, percent: int = 85, n_blocks: int | None = None, group: int = GROUP) -> DataFrame:
    """doc_id, n_shingles, component_id (the least id reachable over links) and n_equal (documents with an equal set).

    Documents with fewer words than a shingle are one shingle; without words (null, empty) they are linked with nothing. Copies are
    represented by their least id; links are searched between distinct sets only. A null id counts as the largest, and its component is
    null unless it is linked. All rows stay, repeated ones too; other columns aren't read. An empty table gives an empty result.
    """
    shingled = written(exchange(docs, ShingleKernel(size, percent), n_blocks), "shingles")
    node = F.coalesce("doc_id", F.lit(int(NO_ID)))
    some = shingled.where("n_shingles > 0")
    equal = some.groupBy("one", "two", "n_shingles").agg(F.min(node).alias("rep"), F.count(F.lit(1)).alias("n_equal"))
    leads = some.where(F.col("tokens").isNotNull()).select("one", "two", "n_shingles", node.alias("rep"), "prefix", "tokens")
    # the first of equal sets in each block has the tokens; of those, the least id represents them
    best = leads.groupBy("one", "two", "n_shingles").agg(F.min("rep").alias("rep"))
    sets = leads.join(best, ["one", "two", "n_shingles", "rep"], "left_semi")
    roots = connected(group_links(sets, percent, group))
    named = equal.join(roots, F.col("rep") == F.col("node"), "left").select(F.col("one").alias("_one"), F.col("two").alias("_two"), F.col("n_shingles").alias("_n"), F.coalesce("root", "rep").alias("component"), "n_equal")
    out = shingled.select("doc_id", "n_shingles", "one", "two").join(named, (F.col("one") == F.col("_one")) & (F.col("two") == F.col("_two")) & (F.col("n_shingles") == F.col("_n")), "left")
    component = F.coalesce("component", "doc_id")
    return out.select("doc_id", "n_shingles", F.when(component != F.lit(int(NO_ID)), component).alias("component_id"), F.coalesce("n_equal", F.lit(1)).alias("n_equal"))
