"""Token counts by rank-synchronous array merging for a byte-level pair-merge vocabulary.

Pre-tokens of a batch that weren't seen yet are held together as ragged arrays and merged at once
(see merges); a document's count is the sum over its pre-tokens, from a cache of bounded size.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .merges import PairTable, merge_words

#: Fixed value: how byte-level vocabularies of this kind cut text before merging.
PRE_TOKENS = regex.compile(r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+""")
MOST_CACHED = 500_000
LONGEST_CACHED = 64
LIMIT = 1024


def tokenizer_path(name: str) -> str:
    """Where the public tokenizer files of this machine lie."""
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_letters() -> dict[int, str]:
    """The printable character that stands for each byte: itself if printable, else the next from U+0100."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out = {b: chr(b) for b in plain}
    rest = (b for b in range(256) if b not in out)
    return out | {b: chr(256 + k) for k, b in enumerate(rest)}


class ByteMerges:
    """Counts tokens exactly as the vocabulary's own library does, special strings included."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab = spec["model"]["vocab"]
        merges = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.table = PairTable({(vocab[a], vocab[b]): (k, vocab[a + b]) for k, (a, b) in reversed(list(enumerate(merges)))})
        self.byte = np.array([vocab[c] for _, c in sorted(byte_letters().items())], np.int64)
        special = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(map(regex.escape, special))) if special else None
        self.marks = special
        self.cache: dict[str, int] = {}

    def counts(self, texts: list[str]) -> list[int]:
        found, out = [], []
        for t in texts:
            n = 0
            parts = [t]
            if self.special and any(s in t for s in self.marks):
                n = len(self.special.findall(t))
                parts = self.special.split(t)
            found.append([w for p in parts for w in PRE_TOKENS.findall(p)] if len(parts) > 1 else PRE_TOKENS.findall(t))
            out.append(n)
        new = list(set().union(*found).difference(self.cache)) if found else []
        fresh = dict(zip(new, self._merged(new)))
        self.cache.update(fresh)
        for k, words in enumerate(found):
            out[k] += sum(map(self.cache.__getitem__, words))
        if len(self.cache) > MOST_CACHED:
            self.cache.clear()
        else:
            for w in new:
                if len(w) > LONGEST_CACHED:
                    del self.cache[w]
        return out

    def _merged(self, words: list[str]) -> list[int]:
        out: list[int] = []
        batch: list[list[int]] = []
        held = 0
        for w in words:
            batch.append(self.byte[np.frombuffer(w.encode("utf-8", "surrogatepass"), np.uint8)].tolist())
            held += len(batch[-1])
            if held > 500_000:
                out += [len(x) for x in merge_words(batch, self.table)]
                batch, held = [], 0
        return out + [len(x) for x in merge_words(batch, self.table)]


_LOADED: dict[str, ByteMerges] = {}


def count_tokens(docs: DataFrame, path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """Per row: doc_id, n_bytes (UTF-8), n_tokens, over_limit.

    Whole texts; null and empty ones have 0 bytes and 0 tokens.  Rows are counted one by one, so repeated
    ids, ties and other columns change nothing; doc_id may be null.
    path: a byte-level tokenizers file, at the same place on every machine.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        file = path or tokenizer_path("byte_bpe_50k.json")
        if file not in _LOADED:
            _LOADED[file] = ByteMerges(file)
        counter = _LOADED[file]
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                texts = [x or "" for x in part.column(1).to_pylist()]
                n = counter.counts(texts)
                size = [len(t.encode("utf-8", "surrogatepass")) for t in texts]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(size, pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def op4_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(common.read(spark, sf_dir, "documents"))
