"""Quality classifier: similarity-weighted votes of the nearest labelled documents in a latent-semantic space.

A document's terms are its words (lower-cased, without the marks at their ends, hashed to LEXICAL places), its
character-shape trigrams (letters by case, digits, each punctuation mark, blanks) and how much of it repeats.
Counts become square-rooted shares of their block (words, shapes), weighted by inverse document frequency.  The
latent space is spanned by the leading right singular vectors of the labelled sample's matrix, found by randomised
subspace iteration in blocks of rows.  The labelled vectors are broadcast (at most MOST_LABELLED x DIMENSIONS
floats) and every document is compared with all of them in blocks.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: The classifier is fitted on at most so many labelled documents, taken in the order of a hash of doc_id.
MOST_LABELLED = 6000
DIMENSIONS = 64
LEXICAL = 8192
SHAPES = 1024
#: Beside the words and shapes: letters of words that repeat the word before, and of lines that occurred before.
TERMS = LEXICAL + SHAPES + 2
#: What words weigh beside shapes.
WORD_SHARE = 0.5
NEIGHBOURS = 25
POWER = 4
THRESHOLD = 0.7
HELD_OUT = 2  # crc32(doc_id) mod 4
BLOCK = 256
SEED = 5
MOST_CACHED = 300_000

_CLASSES = 40
_MARKS = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


def _shapes() -> bytes:
    """Class of each UTF-8 byte: lower, upper, digit, accented, blank, line end, 32 punctuation marks, other."""
    out = bytearray([39] * 256)
    marks = 6
    for b in range(256):
        c = chr(b)
        if "a" <= c <= "z":
            out[b] = 0
        elif "A" <= c <= "Z":
            out[b] = 1
        elif "0" <= c <= "9":
            out[b] = 2
        elif b >= 0xC0:
            out[b] = 3
        elif c in " \t":
            out[b] = 4
        elif c in "\n\r":
            out[b] = 5
        elif 32 < b < 127:
            out[b] = marks
            marks += 1
    return bytes(out)


_SHAPE, _INNER = _shapes(), bytes(range(0x80, 0xC0))
_HASHED = (np.arange(_CLASSES**3, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(54)).astype(np.int64)  # 0..1023
_PLACES: dict[bytes, int] = {}


def _place(word: bytes) -> int:
    core = word.strip(_MARKS) or word
    return zlib.crc32(core.decode("utf-8", "surrogatepass").lower().encode("utf-8", "surrogatepass")) % LEXICAL


def terms(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(places, counts) of the terms of a whole text; none for texts of fewer than three characters."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    c = np.frombuffer(raw.translate(_SHAPE, _INNER), np.uint8).astype(np.int64)
    if len(c) < 3:
        return np.empty(0, np.int32), np.empty(0, np.float32)
    words = raw.split()
    if len(_PLACES) > MOST_CACHED:
        _PLACES.clear()
    n = Counter(words)
    for w in [w for w in n if w not in _PLACES]:
        _PLACES[w] = _place(w)
    lexical = np.bincount(np.fromiter(map(_PLACES.__getitem__, n), np.int64, len(n)), weights=np.fromiter(n.values(), np.float64, len(n)), minlength=LEXICAL)
    shapes = np.bincount(_HASHED[(c[:-2] * _CLASSES + c[1:-1]) * _CLASSES + c[2:]], minlength=SHAPES)
    again, seen = 0, set()
    for line in raw.split(b"\n"):
        if line in seen:
            again += len(line)
        seen.add(line)
    whole = np.concatenate([lexical, shapes, [sum(len(a) for a, b in zip(words, words[1:]) if a == b), again]]).astype(np.float32)
    at = np.flatnonzero(whole)
    return at.astype(np.int32), whole[at]


def matrix(rows: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """The rows as a dense block of counts."""
    out = np.zeros((len(rows), TERMS), np.float32)
    for k, (at, n) in enumerate(rows):
        out[k, at] = n
    return out


class NeighbourVote:
    """The fitted classifier; score() gives the weighted share of label 1 among the nearest vectors."""

    def __init__(self, rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, dimensions: int = DIMENSIONS, neighbours: int = NEIGHBOURS):
        self.labels = labels.astype(np.float32)
        self.prior = float(self.labels.mean()) if len(labels) else 0.5
        self.neighbours = min(neighbours, len(labels))
        seen = np.zeros(TERMS)
        for at, _ in rows:
            seen[at] += 1
        self.weight = (np.log((1 + max(1, len(rows))) / (1 + seen)) + 1).astype(np.float32)
        blocks = [rows[k : k + BLOCK] for k in range(0, len(rows), BLOCK)]
        self.axes = np.random.default_rng(SEED).standard_normal((TERMS, min(dimensions + 8, TERMS))).astype(np.float32)
        for _ in range(5):  # subspace iteration on X'X, orthonormal after each
            new = np.zeros_like(self.axes)
            for b in blocks:
                x = self._weighted(matrix(b))
                new += x.T @ (x @ self.axes)
            q, r = np.linalg.qr(new)
            self.axes = q
        order = np.argsort(-np.abs(np.diag(r)))[:dimensions] if blocks else np.arange(dimensions)
        self.axes = np.ascontiguousarray(self.axes[:, order], np.float32)
        self.vectors = np.concatenate([self.places(matrix(b)) for b in blocks]) if blocks else np.zeros((0, dimensions), np.float32)

    def _weighted(self, counts: np.ndarray) -> np.ndarray:
        """Each block of terms as unit vectors of weighted shares, side by side."""
        out = np.empty_like(counts)
        for part, share in ((slice(0, LEXICAL), WORD_SHARE), (slice(LEXICAL, TERMS), 1.0)):
            c = counts[:, part]
            out[:, part] = self._unit(np.sqrt(c / np.maximum(c.sum(axis=1, keepdims=True), 1)) * self.weight[part]) * np.float32(share)
        return out

    @staticmethod
    def _unit(x: np.ndarray) -> np.ndarray:
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)

    def places(self, counts: np.ndarray) -> np.ndarray:
        """Unit vectors in the latent space."""
        return self._unit(self._weighted(counts) @ self.axes)

    def score(self, counts: np.ndarray) -> np.ndarray:
        if not len(self.labels):
            return np.full(len(counts), 0.5)
        sim = self.places(counts) @ self.vectors.T
        near = np.argpartition(-sim, self.neighbours - 1, axis=1)[:, : self.neighbours] if self.neighbours < sim.shape[1] else np.broadcast_to(np.arange(sim.shape[1]), sim.shape)
        w = np.maximum(np.take_along_axis(sim, near, axis=1), 0).astype(np.float64) ** POWER
        total = w.sum(axis=1)
        got = (w * self.labels[near]).sum(axis=1) / np.maximum(total, 1e-12)
        return np.clip(np.where((total > 1e-9) & (counts.sum(axis=1) > 0), got, self.prior), 0.0, 1.0)


def is_held_out(doc_id) -> F.Column:
    return F.coalesce(F.crc32(F.col(doc_id).cast("long").cast("string")) % 4 == HELD_OUT, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED) -> NeighbourVote:
    """Learns from labelled documents that aren't held out, at most `most` of them, wherever they are.

    Labels of a repeated doc_id are averaged, and of its documents the one with the smallest digest of its text
    stands for all; null ids and labels are passed over.
    """
    use = labels.select(F.col("doc_id").cast("long").alias("_id"), F.col("quality").cast("double").alias("_q")).filter("_id is not null and _q is not null")
    use = use.filter(~is_held_out("_id")).groupBy("_id").agg(F.avg("_q").alias("_q"))
    ids = use.orderBy(F.xxhash64("_id"), "_id").limit(most).collect()  # <= most pairs of numbers
    if not ids:
        return NeighbourVote([], np.zeros(0))
    known = F.broadcast(docs.sparkSession.createDataFrame([(r["_id"],) for r in ids], "_id long"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [terms(t.as_py()) for t in b.column(2)]
            cols = [pa.array([x[k].tobytes() for x in got], pa.binary()) for k in (0, 1)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *cols], names=["_id", "digest", "at", "n"])

    found = docs.select(F.col("doc_id").cast("long").alias("_id"), F.col("text").cast("string").alias("_t")).join(known, "_id")
    found = found.select("_id", F.md5(F.coalesce("_t", F.lit("")).cast("binary")).alias("digest"), "_t")
    one = found.mapInArrow(run, "_id long, digest string, at binary, n binary").groupBy("_id").agg(F.min_by(F.struct("at", "n"), "digest").alias("t"))
    got = {r["_id"]: (np.frombuffer(r["at"], np.int32), np.frombuffer(r["n"], np.float32)) for r in one.select("_id", "t.*").collect()}  # <= most rows
    with_text = [(got[r["_id"]], r["_q"] >= 0.5) for r in ids if r["_id"] in got]
    return NeighbourVote([t for t, _ in with_text], np.array([y for _, y in with_text], np.float32))


def _scores(model: NeighbourVote, texts: list[str | None]) -> np.ndarray:
    out = [model.score(matrix([terms(t) for t in texts[lo : lo + BLOCK]])) for lo in range(0, len(texts), BLOCK)]
    return np.concatenate(out) if out else np.empty(0)


def score_documents(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Per row: doc_id, held_out, score, predicted.

    Null and empty texts, and those too short for a trigram, score the labelled share of quality 1; with
    nothing labelled every score is 0.5.  A null doc_id isn't held out.  Rows are scored one by one, so
    repeated ids, ties and other columns change nothing.
    """
    model = fit(docs, labels)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            s = _scores(sent.value, b.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("long"), is_held_out("doc_id").alias("held_out"), F.col("text").cast("string"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Rows of docs that score at least the threshold, with their columns as they are."""
    sent = docs.sparkSession.sparkContext.broadcast(fit(docs, labels))

    @F.pandas_udf("double")
    def score(texts):
        import pandas as pd

        return pd.Series(_scores(sent.value, [t if isinstance(t, str) else None for t in texts]))

    return docs.filter(score(F.col("text").cast("string")) >= threshold)


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(common.read(spark, sf_dir, "documents"), common.read(spark, sf_dir, "labels"))
