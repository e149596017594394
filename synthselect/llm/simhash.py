"""SimHash near-duplicates by deletion-variant signatures.

A 64-bit fingerprint is cut into 3 segments.  Two fingerprints that differ in at most 4 bits have a
segment in which they differ in at most one, so with one wildcard bit in that segment they agree:
each fingerprint is indexed under 64 variants (the wildcard's place and the other bits of its
segment), equal variants meet, and every pair that meets is verified on all 64 bits.

A bucket of more than BLOCK rows is split once more: its fingerprints agree in one segment but for a bit, and
of the other bits, cut into 5, two that are linked share one part whole.  What is still too large is
compared in pairs of blocks.

Distinct fingerprints are the nodes, so exact copies cost nothing; a bucket's links leave as a star,
so no group is expanded into pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

SEGMENTS = 3
WORDS = 4
MOST_BITS = 4
SEED = 42
#: Rows of a bucket that are compared in one task.
BLOCK = 2048


def fingerprint(text: str | None, words: int = WORDS, seed: int = SEED) -> int:
    """Signed 64-bit SimHash of a whole text; null and wordless texts give 0."""
    if not text:
        return 0
    w = text.encode("utf-8", "surrogatepass").lower().split()  # bytes: only A-Z and the six ASCII blanks count
    if not w:
        return 0
    n = len(w) - words + 1
    if n <= 1:
        return int(np.uint64(xxhash.xxh64_intdigest(b" ".join(w), seed)).astype(np.int64))
    whole = b" ".join(w)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1)
    first = np.concatenate([[0], ends[: n - 1]]).tolist()
    last = (ends[words - 1 :] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(whole[i:j], seed) for i, j in zip(first, last)), np.uint64, n)
    set_ = np.zeros(64, np.int64)
    for k in range(0, n, 65536):
        set_ += np.unpackbits(h[k : k + 65536].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(set_ * 2 > n).view(">u8")[0].astype(np.int64))


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp long) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.fromiter(map(fingerprint, (x.as_py() for x in b.column(1))), np.int64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps)], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, fp long")


def _segments() -> list[tuple[int, int]]:
    """(lowest bit, width) of the 3 segments of 64 bits."""
    cuts = [64 * k // SEGMENTS for k in range(SEGMENTS + 1)]
    return [(lo, hi - lo) for lo, hi in zip(cuts, cuts[1:])]


def variants(fps: DataFrame) -> DataFrame:
    """64 rows (key, fp) for each distinct fp: the wildcard's bit above, the segment without it below."""
    keys = []
    for lo, width in _segments():
        for bit in range(width):
            mask = ((1 << width) - 1) & ~(1 << bit)
            keys.append(f"({(lo + bit) << 32}L | (shiftrightunsigned(fp, {lo}) & {mask}L))")
    return fps.select(F.explode(F.expr(f"array({', '.join(keys)})")).alias("key"), "fp")


def finer(rows: DataFrame) -> DataFrame:
    """5 rows (key, fp) for each: the bucket and one of the 5 parts of the bits outside its segment."""
    at = F.shiftrightunsigned("key", 32)
    rest = F.lit(0).cast("long")
    for lo, width in _segments():
        above = f"shiftleft(shiftrightunsigned(fp, {lo + width}), {lo})" if lo + width < 64 else "0L"
        rest = F.when((at >= lo) & (at < lo + width), F.expr(f"(fp & {(1 << lo) - 1}L) | {above}")).otherwise(rest)
    cuts = [43 * k // 5 for k in range(6)]
    parts = [F.xxhash64("key", F.lit(k), F.shiftrightunsigned("_rest", lo).bitwiseAND((1 << (hi - lo if k < 4 else hi - lo + 1)) - 1)) for k, (lo, hi) in enumerate(zip(cuts, cuts[1:]))]
    return rows.withColumn("_rest", rest).select(F.explode(F.array(*parts)).alias("key"), "fp")


def links(fps: DataFrame, most_bits: int = MOST_BITS) -> DataFrame:
    """Verified links (a, b) between distinct fingerprints; each bucket's links as a star."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf, starts in common.whole_runs(batches, ["key", "bi", "bj"]):
            fp, mine = pdf["fp"].to_numpy(), pdf["mine"].to_numpy()
            cross = pdf["bi"].to_numpy() != pdf["bj"].to_numpy()
            bits = fp.view(np.uint64)
            xs, ys = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
            for i, j in common.pairs_in_runs(starts, len(pdf)):
                ok = np.bitwise_count(bits[i] ^ bits[j]) <= most_bits
                ok &= ~cross[i] | (mine[i] != mine[j])
                if ok.sum() > 100_000:
                    x, y = common.stars(fp[i[ok]], fp[j[ok]])
                else:
                    x, y = fp[i[ok]], fp[j[ok]]
                xs.append(x)
                ys.append(y)
            a, b = common.stars(np.concatenate(xs), np.concatenate(ys))
            yield pd.DataFrame({"a": a, "b": b})

    fps = fps.select("fp").distinct()
    rows = variants(fps)
    hot = common.land(rows.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > BLOCK).select("key"), "hot")
    if hot.limit(1).count():
        hot = common.sent(hot)
        rows = rows.join(hot, "key", "left_anti").union(finer(rows.join(hot, "key", "left_semi")))
        rows = common.in_blocks(rows, "key", "fp", BLOCK)
    else:
        rows = rows.withColumns({"mine": F.lit(0), "bi": F.lit(0), "bj": F.lit(0)}).repartition("key").sortWithinPartitions("key")
    return rows.mapInPandas(run, "a long, b long")


def simhash_groups(docs: DataFrame, most_bits: int = MOST_BITS) -> DataFrame:
    """Per row: doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable by links).

    Null and empty texts have fingerprint zero and are linked like any other.  Rows that share a
    doc_id are told apart by their text.  A null doc_id keeps its row; its component has the smallest
    doc_id that is not null, or null.  Columns other than doc_id and text are not looked at.
    """
    found = common.land(fingerprints(docs), "simhash")
    root = common.components(links(found.select("fp"), most_bits))
    low = found.groupBy("fp").agg(F.min("doc_id").alias("low"), F.count(F.lit(1)).alias("n"))
    low = low.join(root, low.fp == root.id, "left").select("fp", "low", F.coalesce("root", "fp").alias("root"), "n")
    low = common.land(low, "classes")
    ids = low.groupBy("root").agg(F.min("low").alias("component_id"), F.count(F.lit(1)).alias("_n"))
    of = common.join_spread(low.select("fp", "root", "n"), ids, "root", "_n", low.count()).select("fp", "component_id", F.col("n").alias("_n"))
    out = common.join_spread(found, of, "fp", "_n", found.count())
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def near_dedup(docs: DataFrame) -> DataFrame:
    """Rows of docs whose doc_id is the smallest of its group (null ids stay); of repeated ids all rows stay."""
    g = simhash_groups(docs).filter("doc_id = component_id").select(F.col("doc_id").alias("_kept")).distinct()
    return docs.join(g, docs.doc_id.eqNullSafe(g._kept), "left_semi").unionByName(docs.filter("doc_id is null"))


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_groups(common.read(spark, sf_dir, "documents"))
