"""The default at scale: k-mer seeds, then doubling of what still ties, with large groups re-ranked by range."""

from __future__ import annotations

import time

import numpy as np
from suffix_engine.model import Corpus
from suffix_engine.operators import doubling, kmers
from suffix_engine.session import cut, cut_by

def build(corpus: Corpus, k: int | None = None, most: int = doubling.MOST_IN_GROUP) -> doubling.Result:
    """Inverse suffix array: seeds of k symbols, then rounds over unresolved suffixes only, until none is left. Groups of over most members
    are re-ranked by range instead of in one task, with the same ranks."""
    h = k or kmers.widest(corpus)
    began = time.perf_counter()
    ranks = cut_by(doubling.init_ranks(corpus, h), "pos")
    history = [doubling._measured(ranks, 0, h, began)]
    for number in range(1, int(np.ceil(np.log2(max(corpus.n, 2)))) + 1):
        left = history[-1].unresolved
        if not left:
            break
        began = time.perf_counter()
        pairs = doubling.pair_by_join(ranks.where("tied"), ranks, h)
        new = cut(doubling.rerank_in_groups(pairs) if left <= most else doubling.rerank_mixed(cut(pairs), most))
        ranks = cut_by(doubling.with_new(ranks, new))
        h *= 2
        history.append(doubling._measured(new, number, h, began, corpus.n))
    return doubling.Result(ranks.select("pos", "rnk"), history)
