"""Words of texts in Python workers: a text is split once a pass, where Spark's lambdas take it a word at a time."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Entries of a worker's table of words before it is begun anew.
MOST_KNOWN = 500_000


def is_odd(text: Column) -> Column:
    """Whether the text holds letters beyond ASCII, whose lower case may differ between engines or with their surroundings."""
    return F.octet_length(text) != F.length(text)


def lowered(text: Column | str) -> Column:
    """The text lower-cased by Spark where Python may lower it otherwise, else null."""
    text = F.col(text) if isinstance(text, str) else text
    return F.when(is_odd(text), F.lower(text))


def split(text: str, low: str | None = None) -> list[str]:
    """The same as functions.words(); low: what lowered() gave."""
    return [w for w in (text.lower() if low is None else low).replace("\n", " ").split(" ") if w]


def unit(*parts: object) -> int:
    """The same as functions.hash_unit()."""
    return int.from_bytes(hashlib.md5("-".join(map(str, parts)).encode()).digest()[:4])


class Ids(dict):
    """Hashed ids 0..v-1 of words, the same as reference.word_ids()."""

    def __init__(self, v: int, seed: str = "ref"):
        super().__init__()
        self.v, self.seed = v, f"{seed}-"

    def __missing__(self, word: str) -> int:
        if len(self) >= MOST_KNOWN:
            self.clear()
        out = self[word] = int.from_bytes(hashlib.md5((self.seed + word).encode()).digest()[:4]) % self.v
        return out


class Runs:
    """Runs of n words, to be looked for in lists of words: of a run, one block of (n + 1) // 2 words begins at a multiple
    of its length in the list, so these blocks are looked up before the runs are."""

    def __init__(self, runs: frozenset[str], n: int = 8):
        self.runs, self.n, self.block = runs, n, (n + 1) // 2
        self.blocks = {" ".join(w[k : k + self.block]) for w in (r.split(" ") for r in runs) for k in range(n - self.block + 1)}

    def found(self, words: list[str]) -> int:
        """How many distinct runs the words hold."""
        b = self.block
        if len(words) < self.n or self.blocks.isdisjoint([" ".join(words[k : k + b]) for k in range(0, len(words) - b + 1, b)]):
            return 0
        return len(self.runs.intersection(map(" ".join, zip(*(words[k:] for k in range(self.n))))))
