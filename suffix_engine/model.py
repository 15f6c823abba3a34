"""Row types that the methods exchange, and the corpus they work on."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame

TEXT = "pos long, code int"
CHUNK = "chunk long, start long, codes binary"
KMER = "kmer long, pos long"
RANKS = "pos long, rnk long, tied boolean"
PAIRS = "pos long, r1 long, r2 long"
SA = "rank long, pos long"
BWT = "rank long, code int"

#: How codes are stored in binary columns.
CODE = np.dtype("<u2")
#: Shown for the terminator.
TERMINATOR = "$"


@dataclass
class Corpus:
    """One text of n symbols with a terminator of its own at the end, stored as pieces (start long, codes binary).

    symbols[c] is the character of code c; the terminator's code is the least or the greatest one, by order.
    """

    pieces: DataFrame
    n: int
    symbols: list[str]
    counts: np.ndarray
    order: str = "smallest"
    documents: DataFrame | None = field(default=None, repr=False)

    @property
    def sigma(self) -> int:
        return len(self.symbols)

    @property
    def terminator(self) -> int:
        return 0 if self.order == "smallest" else self.sigma - 1

    @property
    def smaller(self) -> np.ndarray:
        """For each code, how many symbols of the text are smaller."""
        return np.r_[0, np.cumsum(self.counts)[:-1]].astype(np.int64)
