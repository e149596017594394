"""Embedding near-duplicates by lattice hashing.

Every table projects a vector at random to 8 dimensions and decodes it to a point of the E8 lattice.
The home cell and the neighbouring cells whose points are next nearest are the vector's cells in that
table; vectors with the same label that share a cell meet, and the cosine of every pair that meets is
verified in double precision.  A pair that shares several cells counts in the smallest of them.

Equal vectors of a label are one class with a weight, so copies are never expanded into pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

LEAST_COSINE = 0.93
TABLES = 5
NEIGHBOURS = 2
SCALE = 0.6
SEED = 20
#: Rows of a cell that are compared in one task.
BLOCK = 2048


def decode_e8(x: np.ndarray) -> np.ndarray:
    """Nearest E8 points of the rows of x, doubled so that they are integers.

    E8 is D8 and D8 shifted by one half in every coordinate; D8 has integer points of even sum.
    """

    def d8(y: np.ndarray) -> np.ndarray:
        r = np.rint(y)
        odd = (r.sum(axis=1).astype(np.int64) & 1).astype(bool)
        off = y - r
        far = np.abs(off).argmax(axis=1)
        rows = np.flatnonzero(odd)
        r[rows, far[rows]] += np.where(off[rows, far[rows]] >= 0, 1.0, -1.0)
        return r

    a = d8(x)
    b = d8(x - 0.5) + 0.5
    closer = ((x - a) ** 2).sum(axis=1) <= ((x - b) ** 2).sum(axis=1)
    return np.rint(2 * np.where(closer[:, None], a, b)).astype(np.int64)


def shortest_e8() -> np.ndarray:
    """The 240 shortest E8 vectors, doubled: (+-2, +-2, 0^6) and (+-1)^8 with an even number of minus signs."""
    two = [np.array([2 * s * (k == i) + 2 * t * (k == j) for k in range(8)]) for i in range(8) for j in range(i + 1, 8) for s in (1, -1) for t in (1, -1)]
    signs = 1 - 2 * ((np.arange(256)[:, None] >> np.arange(8)) & 1)
    return np.vstack([two, signs[(signs < 0).sum(axis=1) % 2 == 0]]).astype(np.int64)


class LatticeTables:
    """Projections of one width; cells() gives the codes of all tables."""

    def __init__(self, width: int, tables: int = TABLES, neighbours: int = NEIGHBOURS, scale: float = SCALE, seed: int = SEED):
        rng = np.random.default_rng([seed, width])
        self.maps = rng.standard_normal((tables, width, 8)) / (np.sqrt(8) * scale)
        self.neighbours, self.near = neighbours, shortest_e8()
        self.mix = rng.integers(1, 2**63, (tables, 10), dtype=np.int64) | 1

    def cells(self, unit: np.ndarray, labels: np.ndarray) -> np.ndarray:
        """n x tables*(1+neighbours) int64 codes of label, table and lattice point."""
        out = []
        for m, mix in zip(self.maps, self.mix):
            y = unit @ m
            home = decode_e8(y)
            gain = (y - home / 2) @ self.near.T  # nearest next points: the largest inner product with the rest
            best = np.argpartition(-gain, self.neighbours, axis=1)[:, : self.neighbours] if self.neighbours else np.empty((len(y), 0), np.int64)
            for p in (home, *(home + self.near[best[:, k]] for k in range(self.neighbours))):
                with np.errstate(over="ignore"):
                    code = (p * mix[:8]).sum(axis=1) + labels * mix[8] + mix[9]
                    code ^= code >> 29
                    code *= -4658895280553007687
                    code ^= code >> 32
                out.append(code)
        return np.stack(out, axis=1)


def _classes(emb: DataFrame) -> DataFrame:
    """One row per (label, vector) that can have links: smallest id and number of rows."""
    ok = emb.filter("_label is not null and embedding is not null and size(embedding) > 0")
    ok = ok.filter(F.expr("forall(embedding, x -> x is not null and not isnan(x) and abs(x) < double('infinity')) and exists(embedding, x -> x <> 0)"))
    return ok.groupBy("_label", "embedding").agg(F.min("vec_id").alias("vec_id"), F.count(F.lit(1)).alias("weight"))


def _unit(pdf: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    x = np.array(pdf["embedding"].tolist(), np.float64)
    top = np.abs(x).max(axis=1, keepdims=True)
    x = x / np.where(top > 0, top, 1)  # no overflow in the norm
    return x, x / np.linalg.norm(x, axis=1, keepdims=True)


def similar(emb: DataFrame, least: float = LEAST_COSINE, tables: int = TABLES, neighbours: int = NEIGHBOURS, scale: float = SCALE) -> DataFrame:
    """Per row: vec_id, n_links, component_id, kept.

    Vectors that are null, empty, zero or hold null or non-finite components, and rows without a label,
    link with nothing: n_links 0, their own component, kept.  Repeated rows with one vec_id count as
    vectors of their own in n_links.  Vectors of different widths never link.  A null vec_id gives a row
    of its own with component_id null and kept null.  Other columns aren't looked at.
    """
    base = emb.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>"), F.col("label").cast("long").alias("_label"))
    classes = common.land(_classes(base), "classes")

    def place(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        made: dict[int, LatticeTables] = {}
        for pdf in batches:
            for width, part in pdf.groupby(pdf["embedding"].map(len)):
                if width not in made:
                    made[width] = LatticeTables(width, tables, neighbours, scale)
                for lo in range(0, len(part), 1000):
                    sub = part.iloc[lo : lo + 1000]
                    raw, unit = _unit(sub)
                    codes = made[width].cells(unit, sub["_label"].to_numpy(np.int64))
                    vec, own = [r.tobytes() for r in unit], [r.tobytes() for r in codes]
                    for c in range(codes.shape[1]):
                        yield pd.DataFrame({"cell": codes[:, c], "id": sub["node"].to_numpy(), "weight": sub["weight"].to_numpy(), "unit": vec, "codes": own})

    def meet(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf, starts in common.whole_runs(batches, ["cell", "bi", "bj"], 20_000):
            ids, weight, mine, cell = (pdf[k].to_numpy() for k in ("id", "weight", "mine", "cell"))
            cross = pdf["bi"].to_numpy() != pdf["bj"].to_numpy()
            wide = pdf["unit"].map(len).to_numpy()
            xs, ys = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
            count = np.zeros(len(pdf), np.int64)
            width = int(wide.max())
            unit = np.zeros((len(pdf), width // 8))
            for w in np.unique(wide):
                rows = np.flatnonzero(wide == w)
                unit[rows, : w // 8] = np.frombuffer(b"".join(pdf["unit"].iloc[rows]), np.float64).reshape(len(rows), -1)
            codes = np.frombuffer(b"".join(pdf["codes"]), np.int64).reshape(len(pdf), -1)
            for i, j in common.pairs_in_runs(starts, len(pdf), 200_000):
                ok = (~cross[i] | (mine[i] != mine[j])) & (wide[i] == wide[j])
                i, j = i[ok], j[ok]
                ok = np.einsum("ij,ij->i", unit[i], unit[j]) >= least
                i, j = i[ok], j[ok]
                for k in range(0, len(i), 50_000):
                    a, b = i[k : k + 50_000], j[k : k + 50_000]
                    shared = np.full(len(a), np.iinfo(np.int64).max)
                    for c in range(codes.shape[1]):
                        hit = (codes[b] == codes[a, c][:, None]).any(axis=1)
                        np.minimum(shared, np.where(hit, codes[a, c], shared), out=shared)
                    owner = shared == cell[a]
                    a, b = a[owner], b[owner]
                    np.add.at(count, a, weight[b])
                    np.add.at(count, b, weight[a])
                    x, y = common.stars(ids[a], ids[b])
                    xs.append(x)
                    ys.append(y)
            a, b = common.stars(np.concatenate(xs), np.concatenate(ys))
            got = np.flatnonzero(count)
            yield pd.DataFrame({"a": np.concatenate([a, ids[got]]), "b": np.concatenate([b, ids[got]]), "n": np.concatenate([np.zeros(len(a), np.int64), count[got]])})

    # node: a number for each class that can't clash even where rows share a vec_id
    nodes = classes.withColumn("node", F.xxhash64("_label", "embedding"))
    rows = nodes.select("node", "weight", "embedding", "_label").mapInPandas(place, "cell long, id long, weight long, unit binary, codes binary")
    rows = common.land(rows, "cells")
    found = common.land(common.in_blocks(rows, "cell", "id", BLOCK).mapInPandas(meet, "a long, b long, n long"), "links")
    root = common.components(found.select("a", "b"))
    n = found.filter("n > 0").groupBy("a").agg(F.sum("n").alias("n"))
    ids = nodes.select("node", "_label", "embedding", "weight", "vec_id")
    ids = ids.join(n, ids.node == n.a, "left").join(root, ids.node == root.id, "left")
    ids = ids.select("node", "vec_id", F.expr("weight - 1 + coalesce(n, 0)").alias("n_links"), F.coalesce("root", "node").alias("root"), "weight")
    ids = common.land(ids, "nodes")
    low = ids.groupBy("root").agg(F.min("vec_id").alias("low"), F.count(F.lit(1)).alias("_n"))
    ids = common.join_spread(ids, low, "root", "_n", ids.count()).select("node", "n_links", "low", F.col("weight").alias("_n"))
    can = F.expr("_label is not null and embedding is not null and size(embedding) > 0")
    some = base.filter(can).select("vec_id", F.xxhash64("_label", "embedding").alias("node"))
    alone = base.filter(~can).select("vec_id", F.lit(None).cast("long").alias("n_links"), F.lit(None).cast("long").alias("low"))
    out = common.join_spread(some, ids, "node", "_n", base.count(), "left").select("vec_id", "n_links", "low").union(alone)
    return out.select("vec_id", F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"), F.coalesce("low", "vec_id").alias("component_id")).withColumn("kept", F.expr("vec_id = component_id"))


def op3_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar(common.read(spark, sf_dir, "embeddings"))
