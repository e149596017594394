"""Reference models whose adapter gradients stand for samples: low-rank softmax, low-rank bigram, hashed logistic."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import UNIT, bound, hash_unit, texts, words


def _softmax(z: np.ndarray) -> np.ndarray:
    z = np.exp(z - z.max(axis=-1, keepdims=True))
    return z / z.sum(axis=-1, keepdims=True)


@dataclass
class LowRankSoftmax:
    """p = softmax((W0 + scale B A) x): W0 frozen, A (r x d) and B (C x r) trained."""

    w0: np.ndarray
    a: np.ndarray
    b: np.ndarray
    scale: float = 1.0

    @classmethod
    def start(cls, d: int, classes: int, rank: int = 4, scale: float = 1.0, seed: int = 0) -> LowRankSoftmax:
        """B starts small, not at zero: at zero the gradient of A vanishes."""
        rng = np.random.default_rng(seed)
        return cls(np.zeros((classes, d)), rng.normal(size=(rank, d)) / d**0.5, rng.normal(size=(classes, rank)) * 0.1, scale)

    def loss(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        z = x @ (self.w0 + self.scale * self.b @ self.a).T
        return -np.log(_softmax(z)[np.arange(len(y)), y])

    def gradients(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """n x r(d + C): adapters only, A's part first."""
        e = _softmax(x @ (self.w0 + self.scale * self.b @ self.a).T)
        e[np.arange(len(y)), y] -= 1
        db = self.scale * e[:, :, None] * (x @ self.a.T)[:, None, :]
        da = self.scale * (e @ self.b)[:, :, None] * x[:, None, :]
        return np.concatenate([da.reshape(len(x), -1), db.reshape(len(x), -1)], axis=1)

    def fit(self, df: DataFrame, vector: str, label: str, epochs: int = 5, rate: float = 1.0) -> LowRankSoftmax:
        """Full-batch steps: one summed gradient per task and epoch, in millionths, reaches the driver."""
        model = self
        for _ in range(epochs):

            def run(batches: Iterator[pd.DataFrame], m=model) -> Iterator[pd.DataFrame]:
                total, n = np.zeros(m.a.size + m.b.size), 0
                for pdf in batches:
                    if len(pdf):
                        total += np.rint(m.gradients(np.array(pdf["x"].tolist(), float), pdf["y"].to_numpy()) * UNIT).sum(axis=0)
                        n += len(pdf)
                yield pd.DataFrame({"i": np.arange(len(total) + 1), "g": np.append(total, n).astype(np.int64)})

            rows = df.select(F.col(vector).alias("x"), F.col(label).cast("int").alias("y")).mapInPandas(run, "i int, g long").groupBy("i").agg(F.sum("g").alias("g")).collect()
            g = np.array([r["g"] for r in sorted(rows, key=lambda r: r["i"])], float)
            if not len(g) or not g[-1]:
                return model
            step = rate * g[:-1] / UNIT / g[-1]
            model = LowRankSoftmax(model.w0, model.a - step[: model.a.size].reshape(model.a.shape), model.b - step[model.a.size :].reshape(model.b.shape), model.scale)
        return model

    def full_gradients(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """n x C*d: of the full weight matrix, adapters aside."""
        e = _softmax(x @ (self.w0 + self.scale * self.b @ self.a).T)
        e[np.arange(len(y)), y] -= 1
        return (e[:, :, None] * x[:, None, :]).reshape(len(x), -1)

    def per_sample(self, df: DataFrame, id_col: str, vector: str, label: str, signs: np.ndarray | None = None, full: bool = False) -> DataFrame:
        """(id, g): gradients in millionths, of the adapters or (full) of all weights; with `signs` they are projected
        inside the task."""
        of = self.full_gradients if full else self.gradients

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                g = np.rint(of(np.array(pdf["x"].tolist(), float), pdf["y"].to_numpy()) * UNIT).astype(np.int64)
                yield pd.DataFrame({"id": pdf["id"], "g": list(g if signs is None else g @ signs)})

        return df.select(F.col(id_col).alias("id"), F.col(vector).alias("x"), F.col(label).cast("int").alias("y")).mapInPandas(run, "id long, g array<long>")


def word_ids(tokens: Column, v: int, seed: str = "ref") -> Column:
    """Hashed ids 0..v-1 of an array of words."""
    return F.transform(tokens, lambda w: (F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}-"), w).cast("binary")), 1, 8), 16, 10).cast("long") % v).cast("int"))


def shares(ids: Column, v: int) -> Column:
    """Shares of the ids 0..v-1 in an array, in millionths."""
    return bound(ids, lambda h: F.transform(F.sequence(F.lit(0), F.lit(v - 1)), lambda i: F.floor(F.size(F.filter(h, lambda x: x == i)).cast("long") * UNIT / F.greatest(F.lit(1), F.size(h))).cast("long")))


def pair_codes(df: DataFrame, id_col: str, s: str, v: int, q: str | None = None, loss_on: str = "solution") -> DataFrame:
    """(id, pairs): u * v + w of each word after another; q: the text before s.

    loss_on: solution (words of s only, the first after q's last) or both.
    """
    tail = F.col("_s") if q is None else F.concat("_q", "_s")
    d = df.select(F.col(id_col).alias("id"), word_ids(words(s), v).alias("_s"), *([word_ids(words(q), v).alias("_q")] if q else []))
    d = d.select("id", tail.alias("_t"), (F.greatest(F.lit(0), F.size("_q") - 1) if q and loss_on == "solution" else F.lit(0)).alias("_from"))
    n = F.greatest(F.lit(0), F.size("_t") - 1 - F.col("_from"))  # slices, as a lambda would work _t out anew for every word
    runs = F.zip_with(F.slice("_t", F.col("_from") + 1, n), F.slice("_t", F.col("_from") + 2, n), lambda u, x: u * v + x)
    return d.select("id", F.coalesce(runs, F.array().cast("array<int>")).alias("pairs"))


def pair_counts(pairs: DataFrame, v: int) -> np.ndarray:
    """v x v counts of pair codes over all rows: partial sums meet in at most v * v rows."""
    out = np.zeros(v * v, np.int64)
    for r in pairs.select(F.explode("pairs").alias("c")).groupBy("c").agg(F.count(F.lit(1)).alias("n")).collect():
        out[r["c"]] = r["n"]
    return out.reshape(v, v)


def codes_of(ids: texts.Ids, s: str | None, low_s: str | None, q: str | None = "", low_q: str | None = None, loss_on: str = "solution") -> np.ndarray:
    """pair_codes() of one text, in a worker."""
    if s is None or q is None:
        return np.zeros(0, np.int64)
    before = [ids[w] for w in texts.split(q, low_q)]
    t = np.array(before + [ids[w] for w in texts.split(s, low_s)], np.int64)
    t = t[max(0, len(before) - 1) :] if loss_on == "solution" else t
    return t[:-1] * ids.v + t[1:]


def text_pair_counts(df: DataFrame, text: str, v: int) -> np.ndarray:
    """pair_counts() of pair_codes() of whole texts: each task counts its own, v * v numbers at most."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, total = texts.Ids(v), np.zeros(v * v, np.int64)
        for b in batches:
            for s, low in zip(b.column("s").to_pylist(), b.column("low").to_pylist()):
                c = codes_of(ids, s, low)
                if len(c):
                    total += np.bincount(c, minlength=v * v)
        held = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(held, pa.int32()), pa.array(total[held], pa.int64())], names=["c", "n"])

    out = np.zeros(v * v, np.int64)
    told = df.select(F.col(text).alias("s"), texts.lowered(text).alias("low")).mapInArrow(run, "c int, n long")
    for r in told.groupBy("c").agg(F.sum("n").alias("n")).collect():
        out[r["c"]] = r["n"]
    return out.reshape(v, v)


@dataclass
class LowRankBigram:
    """Row-softmax over hashed next words: logits W0[u] + scale (B A)[u]; W0 frozen, B (V x r) and A (r x V) trained.

    A sample's adapter gradient is a sum over its word pairs, so with integer probabilities and adapters its projection
    is a sum of rows of one V*V x k integer table: exact under any partitioning, and no long vector is ever built.
    """

    w0: np.ndarray
    a: np.ndarray
    b: np.ndarray
    scale: float = 1.0
    #: Adapters are rounded to 1 / grain in gradients.
    grain: int = 1000

    @classmethod
    def start(cls, counts: np.ndarray, rank: int = 4, scale: float = 1.0, seed: int = 0) -> LowRankBigram:
        """W0 from the pair counts of all documents; A random, B small but not zero, or A would have no gradient."""
        rng, v = np.random.default_rng(seed), len(counts)
        return cls(np.log(counts + 1.0), rng.normal(size=(rank, v)) / v**0.5, rng.normal(size=(v, rank)) * 0.05, scale)

    @classmethod
    def fixed(cls, counts: np.ndarray, rank: int = 2, scale: float = 0.5) -> LowRankBigram:
        """Adapters of hashed signs, not trained: any engine can check their gradients."""
        from .influence import signs

        return cls(np.log(counts + 1.0), signs("refA", rank, len(counts)).astype(float), signs("refB", len(counts), rank).astype(float), scale, 1)

    def probabilities(self) -> np.ndarray:
        return _softmax(self.w0 + self.scale * self.b @ self.a)

    def loss(self, counts: np.ndarray) -> float:
        return float(-(counts * np.log(self.probabilities())).sum() / max(1.0, counts.sum()))

    def gradient(self, counts: np.ndarray) -> np.ndarray:
        """Of the mean loss of the counted pairs, by A then B."""
        e = (counts.sum(axis=1, keepdims=True) * self.probabilities() - counts) / max(1.0, counts.sum())
        return np.concatenate([(self.scale * self.b.T @ e).ravel(), (self.scale * e @ self.a.T).ravel()])

    def fit(self, counts: np.ndarray, steps: int = 200, rate: float = 2.0, keep: tuple[int, ...] = ()) -> LowRankBigram | list[LowRankBigram]:
        """Full-batch descent on the adapters.  The loss needs the premium set's pair counts only, so no step reads data.

        keep: steps after which a copy is taken; then the list of copies is returned.
        """
        m, copies = self, []
        for k in range(1, steps + 1):
            g = m.gradient(counts)
            m = LowRankBigram(m.w0, m.a - rate * g[: m.a.size].reshape(m.a.shape), m.b - rate * g[m.a.size :].reshape(m.b.shape), m.scale, m.grain)
            if k in keep:
                copies.append(m)
        return copies if keep else m

    @property
    def width(self) -> int:
        return self.a.size + self.b.size

    def table(self, signs: np.ndarray) -> np.ndarray:
        """V*V x k: what each word pair adds to the projected gradient, in millionths of 1 / grain."""
        v, r = self.b.shape
        a, b = (np.rint(x * self.grain).astype(np.int64) for x in (self.a, self.b))
        sa, sb = signs[: r * v].reshape(r, v, -1), signs[r * v :].reshape(v, r, -1)
        t = np.einsum("ur,rwk->uwk", b, sa) + np.einsum("rw,urk->uwk", a, sb)  # of logit (u, w)
        p = np.rint(UNIT * self.probabilities()).astype(np.int64)
        mean = np.einsum("uw,uwk->uk", p, t)
        return (mean[:, None, :] - UNIT * t).reshape(v * v, -1)

    def per_sample(self, pairs: DataFrame, signs: np.ndarray, per_word: bool = True) -> DataFrame:
        """(id, g) of rows (id, pairs): projected gradients, of the mean loss a word or of the summed loss."""
        sent = pairs.sparkSession.sparkContext.broadcast(self.table(signs))  # V * V * k numbers, sizes of the model

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            table = sent.value
            for pdf in batches:
                g = [table[np.asarray(c, np.int64)].sum(axis=0) if len(c) else np.zeros(table.shape[1], np.int64) for c in pdf["pairs"]]
                if per_word:
                    g = [np.rint(x / max(1, len(c))).astype(np.int64) for x, c in zip(g, pdf["pairs"])]
                yield pd.DataFrame({"id": pdf["id"], "g": g})

        return pairs.select("id", "pairs").mapInPandas(run, "id long, g array<long>")


@dataclass
class HashedLogistic:
    """Logistic regression on shares of hashed words; gradients by its weights (and no bias)."""

    weights: np.ndarray

    @staticmethod
    def cells(df: DataFrame, id_col: str, text: str, label: str, v: int) -> DataFrame:
        """(id, y, x): shares of hashed words in millionths."""
        d = df.select(F.col(id_col).alias("id"), F.col(label).cast("int").alias("y"), word_ids(words(text), v, "log").alias("_h"))
        return d.select("id", "y", shares(F.col("_h"), v).alias("x"))

    @classmethod
    def fit(cls, cells: DataFrame, v: int, epochs: int = 20, rate: float = 20.0) -> HashedLogistic:
        """Full-batch steps; of each task one summed gradient, in millionths, reaches the driver per epoch."""
        model = cls(np.zeros(v))
        for _ in range(epochs):

            def run(batches: Iterator[pd.DataFrame], m=model) -> Iterator[pd.DataFrame]:
                total = np.zeros(v + 1)
                for pdf in batches:
                    if len(pdf):
                        x = np.array(pdf["x"].tolist(), float) / UNIT
                        total[:v] += np.rint((m.predict(x) - pdf["y"].to_numpy()) @ x * UNIT)
                        total[v] += len(pdf)
                yield pd.DataFrame({"i": np.arange(v + 1), "g": total.astype(np.int64)})

            rows = cells.mapInPandas(run, "i int, g long").groupBy("i").agg(F.sum("g").alias("g")).collect()
            g = np.array([r["g"] for r in sorted(rows, key=lambda r: r["i"])], float)
            if not len(g) or not g[-1]:
                return model
            model = cls(model.weights - rate * g[:-1] / UNIT / g[-1])
        return model

    def predict(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-x @ self.weights))

    def per_sample(self, cells: DataFrame) -> DataFrame:
        """(id, g): (p - y) x in millionths."""

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                if len(pdf):
                    x = np.array(pdf["x"].tolist(), float)
                    yield pd.DataFrame({"id": pdf["id"], "g": list(np.rint((self.predict(x / UNIT) - pdf["y"].to_numpy())[:, None] * x).astype(np.int64))})

        return cells.mapInPandas(run, "id long, g array<long>")


def unigram_gradients(df: DataFrame, id_col: str, text: str, v: int = 64, seed: str = "uni") -> DataFrame:
    """(id, i, g): base shares minus the document's shares of hashed words, in millionths; no model to train."""
    t = df.select(F.col(id_col).alias("id"), F.explode(words(text)).alias("w")).select("id", (hash_unit(seed, "w") % v).cast("int").alias("i"))
    n = t.groupBy("id", "i").agg(F.count(F.lit(1)).alias("c"))
    size = n.groupBy("id").agg(F.sum("c").alias("n"))
    base = n.groupBy("i").agg(F.sum("c").alias("bc")).crossJoin(n.agg(F.sum("c").alias("bn"))).select("i", F.floor(F.col("bc") * UNIT / F.col("bn")).alias("base"))
    cells = size.join(F.broadcast(base))  # v rows
    own = cells.join(n, ["id", "i"], "left")
    return own.select("id", "i", (F.col("base") - F.floor(F.coalesce("c", F.lit(0)) * UNIT / F.col("n"))).alias("g"))


def nested(cells: DataFrame) -> DataFrame:
    """(id, i, g) rows to (id, g array) in the order of i."""
    return cells.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "g"))), lambda x: x["g"]).alias("g"))


def logistic_gradients(df: DataFrame, id_col: str, text: str, label: str, v: int = 64, seed: str = "log") -> DataFrame:
    """(id, i, g) at zero weights: (1/2 - y) times the word shares, in millionths; the first step's direction."""
    t = df.select(F.col(id_col).alias("id"), F.col(label).alias("y"), F.explode(words(text)).alias("w")).select("id", "y", (hash_unit(seed, "w") % v).cast("int").alias("i"))
    n = t.groupBy("id", "y", "i").agg(F.count(F.lit(1)).alias("c"))
    size = n.groupBy("id").agg(F.sum("c").alias("n"))
    return n.join(size, "id").select("id", "i", ((1 - 2 * F.col("y")) * F.floor(F.col("c") * UNIT / F.col("n"))).cast("long").alias("g"))
