"""License scans: MinHash bands over overlapping text windows retrieve templates, exact containment verifies.

Templates of similar length form a class with windows of its own: blocks of `hop` shingles, so many per
window that every run as long as the class's longest template lies within one.  A window that holds 80 %
of a template's shingles then has at least a known Jaccard likeness to it, and the class's bands are so
many that such a window shares one with probability 0.999 or more.

A text without any shingle of any template shares no band with one, so only the others get signatures.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .license_texts import TEMPLATES

WORDS = 5
LEAST = 0.8
SURE = 0.999
WORD = re.compile(r"[^\W_]+")
MOST_CACHED = 400_000
SPREAD = 1.25
_MIX = np.uint64(0x9E3779B97F4A7C15)


def _mixed(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(31))
    h = h * _MIX
    return h ^ (h >> np.uint64(29))


def _sliding(x: np.ndarray, n: int) -> np.ndarray:
    """Minimum of each n neighbours, by doubling."""
    size = 1
    while 2 * size <= n:
        x = np.minimum(x[:-size], x[size:])
        size *= 2
    return np.minimum(x[: len(x) - (n - size)], x[n - size :]) if size < n else x


class Shingler:
    """64-bit hashes of the five-word shingles of texts; words are lower-cased runs of letters and digits."""

    def __init__(self) -> None:
        self.cache: dict[str, int] = {}

    def words(self, text: str) -> list[str]:
        return WORD.findall(text.lower())

    def hashes(self, words: list[str]) -> np.ndarray:
        cache = self.cache
        for w in set(words).difference(cache):
            cache[w] = xxhash.xxh64_intdigest(w.encode("utf-8", "surrogatepass"), 1)
        h = np.fromiter(map(cache.__getitem__, words), np.uint64, len(words))
        if len(cache) > MOST_CACHED:
            cache.clear()
        if len(h) < WORDS:
            return np.empty(0, np.uint64)
        out = h[: len(h) - WORDS + 1].copy()
        for j in range(1, WORDS):
            out = _mixed(out) + h[j : len(h) - WORDS + 1 + j]
        return _mixed(out)


class Bands:
    """One class: its templates, window geometry and band keys."""

    def __init__(self, members: dict[int, np.ndarray], longest: int, least: float, sure: float, seed: int):
        """longest: shingles of the longest template, repeats included."""
        self.members = members
        self.hop = max(1, longest // 8)
        self.blocks = longest if self.hop == 1 else -(-longest // self.hop) + 1
        width = self.hop * self.blocks
        self.likeness = min(need / (len(t) + width - need) for t in members.values() for need in [math.ceil(least * len(t))])
        self.rows = 1 if self.likeness > 0.99 or self.likeness < 0.3 else 2
        p = self.likeness**self.rows
        self.bands = 1 if p > sure else math.ceil(math.log(1 - sure) / math.log(1 - p))
        rng = np.random.default_rng(seed)
        self.salts = rng.integers(0, 2**63, self.rows * self.bands, dtype=np.uint64)
        keys, of = [], []
        for k, t in members.items():
            low = np.array([_mixed(t ^ f).min() for f in self.salts], np.uint64)
            keys.append(self._keys(low[:, None])[:, 0])
            of.append(k)
        order = np.argsort(np.array(keys), axis=0)  # templates x bands
        self.keys, self.of = np.take_along_axis(np.array(keys), order, axis=0), np.array(of)[order]

    def _keys(self, low: np.ndarray) -> np.ndarray:
        """Band keys of signatures (hashes x windows)."""
        k = low[0 :: self.rows]
        for r in range(1, self.rows):
            k = _mixed(k) + low[r :: self.rows]
        return _mixed(k)

    def candidates(self, h: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
        """(first shingle, end, template) of the windows that share a band with a template; number of windows.

        h: shingles of all documents; sizes: shingles of each, all positive.
        """
        first = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        nb = -(-sizes // self.hop)
        at = np.repeat(first - np.concatenate([[0], np.cumsum(nb * self.hop)[:-1]]), nb) + np.arange(nb.sum()) * self.hop
        nw = np.maximum(nb - self.blocks + 1, 1)
        b0 = np.concatenate([[0], np.cumsum(nb)[:-1]])
        lo = np.repeat(b0 - np.concatenate([[0], np.cumsum(nw)[:-1]]), nw) + np.arange(nw.sum())
        hi = np.minimum(lo + self.blocks, np.repeat(b0 + nb, nw))
        whole = np.repeat(nb >= self.blocks, nw)  # else the document is one shorter window
        edges = np.stack([lo[~whole], hi[~whole]], axis=1).ravel()
        low = np.empty((len(self.salts), len(lo)), np.uint64)
        for k, f in enumerate(self.salts):
            block = np.minimum.reduceat(_mixed(h ^ f), at) if self.hop > 1 else _mixed(h ^ f)
            low[k, whole] = _sliding(block, self.blocks)[lo[whole]] if len(block) >= self.blocks else 0
            if len(edges):
                low[k, ~whole] = np.minimum.reduceat(np.append(block, np.uint64(0)), edges)[::2]
        keys = self._keys(low)
        rows, temps = [], []
        for b in range(self.bands):  # look every window's key up among the templates' sorted keys
            first_, last = (np.searchsorted(self.keys[:, b], keys[b], side=x) for x in ("left", "right"))
            hit = np.flatnonzero(last > first_)
            n = last[hit] - first_[hit]
            rows.append(np.repeat(hit, n))
            temps.append(self.of[np.repeat(first_[hit], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n), b])
        found = np.unique(np.stack([np.concatenate(rows), np.concatenate(temps)]), axis=1)
        ends = np.append(at, len(h))
        doc_end = np.repeat(first + sizes, nw)[found[0]]
        return ends[lo[found[0]]], np.minimum(ends[hi[found[0]]], doc_end), found[1], len(lo)


class LicenseIndex:
    def __init__(self, templates: dict[str, str] | None = None, least: float = LEAST, sure: float = SURE):
        self.shingler, self.least = Shingler(), least
        self.names = list(templates or TEMPLATES)
        runs = [self.shingler.hashes(self.shingler.words(t)) for t in (templates or TEMPLATES).values()]
        sets = [np.unique(h) for h in runs]
        if any(not len(s) for s in sets):
            raise ValueError(f"a template has at least {WORDS} words")
        self.sets = sets
        self.known = np.unique(np.concatenate(sets))
        self.maybe = np.zeros(1 << 20, bool)
        self.maybe[(self.known >> np.uint64(44)).astype(np.int64)] = True
        self.classes: list[Bands] = []
        left = sorted(range(len(sets)), key=lambda k: len(sets[k]))
        while left:
            most = max(len(sets[left[0]]), int(SPREAD * len(sets[left[0]])))
            group = [k for k in left if len(sets[k]) <= most]
            left = [k for k in left if k not in group]
            self.classes.append(Bands({k: sets[k] for k in group}, max(len(runs[k]) for k in group), least, sure, 7 + len(self.classes)))

    def _holds(self, h: np.ndarray) -> bool:
        """Whether any of the shingles is one of a template."""
        h = h[self.maybe[(h >> np.uint64(44)).astype(np.int64)]]
        return bool(len(h)) and bool((self.known[np.minimum(np.searchsorted(self.known, h), len(self.known) - 1)] == h).any())

    def scan(self, texts: list[str]) -> list[tuple[int, int, list[tuple[str, int, int, float]]]]:
        """For each text: windows, candidates, matches (license, first word, end word, containment)."""
        hs = [self.shingler.hashes(self.shingler.words(t)) for t in texts]
        windows = np.zeros(len(texts), np.int64)
        lengths = np.array([len(h) for h in hs], np.int64)
        for c in self.classes:
            windows[lengths > 0] += np.maximum(-(-lengths[lengths > 0] // c.hop) - c.blocks + 1, 1)
        some = [k for k, h in enumerate(hs) if len(h) and self._holds(h)]
        if not some:
            return [(int(n), 0, []) for n in windows]
        sizes = np.array([len(hs[k]) for k in some])
        h = np.concatenate([hs[k] for k in some])
        first = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        cands = np.zeros(len(texts), np.int64)
        best: dict[tuple[int, int], list[tuple[int, int]]] = {}
        for c in self.classes:
            lo, hi, temp, _ = c.candidates(h, sizes)
            doc = np.searchsorted(first, lo, side="right") - 1
            for a, e, t, d in zip(lo.tolist(), hi.tolist(), temp.tolist(), doc.tolist()):
                cands[some[d]] += 1
                hit = np.flatnonzero(np.isin(h[a:e], self.sets[t]))
                share = len(np.unique(h[a:e][hit])) / len(self.sets[t])
                if share >= self.least:
                    start = a - int(first[d])
                    best.setdefault((some[d], t), []).append((start + int(hit[0]), start + int(hit[-1]) + WORDS))
        found: dict[int, list[tuple[str, int, int, float]]] = {}
        for (d, t), spans in best.items():
            spans.sort()
            merged: list[list] = []
            for s, e in spans:  # windows overlap: one place is told once
                if merged and s < merged[-1][1]:
                    merged[-1][1] = max(e, merged[-1][1])
                else:
                    merged.append([s, e])
            for s, e in merged:
                share = len(np.intersect1d(hs[d][s : e - WORDS + 1], self.sets[t])) / len(self.sets[t])
                found.setdefault(d, []).append((self.names[t], s, e, share))
        return [(int(windows[k]), int(cands[k]), sorted(found.get(k, []), key=lambda m: (m[1], m[2], m[0]))) for k in range(len(texts))]


_LOADED: dict[str, LicenseIndex] = {}


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, least: float = LEAST) -> DataFrame:
    """Per row: doc_id, n_windows, n_candidates, n_matches, licenses, spans, best.

    licenses: names, sorted, comma-joined; spans: name:first word:end word in text order; best: largest
    containment of a template, 0 without match.  Null and empty texts and texts of fewer than five words
    match nothing.  Rows are scanned one by one, so repeated ids, ties and other columns change nothing;
    doc_id may be null.  The templates are the caller's table of names and texts, at most some thousands.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key = repr((templates and sorted(templates.items()), least))
        if key not in _LOADED:
            _LOADED[key] = LicenseIndex(templates, least)
        index = _LOADED[key]
        for b in batches:
            ids, texts = b.column(0), [t or "" for t in b.column(1).to_pylist()]
            lo = 0
            while lo < len(texts):
                hi, held = lo, 0
                while hi < len(texts) and (hi == lo or held + len(texts[hi]) < 250_000):
                    held += len(texts[hi])
                    hi += 1
                got = index.scan(texts[lo:hi])
                cols = [
                    ids.slice(lo, hi - lo), pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.int64()), pa.array([len(g[2]) for g in got], pa.int64()),
                    pa.array([",".join(sorted({m[0] for m in g[2]})) for g in got], pa.string()), pa.array([",".join(f"{m[0]}:{m[1]}:{m[2]}" for m in g[2]) for g in got], pa.string()),
                    pa.array([max((m[3] for m in g[2]), default=0.0) for g in got], pa.float64()),
                ]
                yield pa.RecordBatch.from_arrays(cols, names=names)
                lo = hi

    names = ["doc_id", "n_windows", "n_candidates", "n_matches", "licenses", "spans", "best"]
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_windows long, n_candidates long, n_matches long, licenses string, spans string, best double")


def op5_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(common.read(spark, sf_dir, "documents"))
