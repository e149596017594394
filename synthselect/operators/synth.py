"""Synthesizers: providers of (q, s) pairs from snippets, pure functions of snippet, checkpoint, draw and seed."""

from __future__ import annotations

import time
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import hash_unit, normalise, texts, words
from ..sources import MOST_SENT, join_sent, land
from . import candidates

#: Words of the passage that an n-gram synthesizer is prompted with.
PASSAGE = 12


class PassageSynthesizer:
    """Hash-placed windows of the snippet: the whole chain can be checked by SQL."""

    def generate(self, snippets: DataFrame, ckpts: list[int], draws: int) -> DataFrame:
        return candidates.passages(candidates.grid(snippets, ckpts, draws))

    def train(self, samples: DataFrame, n_ckpt: int) -> PassageSynthesizer:
        return self


@dataclass
class EndpointSynthesizer:
    """Any callable of (snippets, ckpt, draw) batches, for instance a served model; what it gives is landed, not asked anew.

    retries: further tries after an error of the network or a time-out, with growing pauses; rate: most calls a second
    of one task; batch: rows a call.
    """

    call: Callable[[pd.Series, pd.Series, pd.Series], pd.DataFrame]
    retries: int = 3
    rate: float | None = None
    batch: int = 64
    pause: float = 0.5

    def generate(self, snippets: DataFrame, ckpts: list[int], draws: int) -> DataFrame:
        cells = candidates.grid(snippets, ckpts, draws)

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            free = 0.0
            for whole in batches:
                for lo in range(0, len(whole), self.batch):
                    pdf = whole.iloc[lo : lo + self.batch]
                    for left in range(self.retries, -1, -1):
                        if self.rate:
                            time.sleep(max(0.0, free - time.monotonic()))
                            free = time.monotonic() + 1 / self.rate
                        try:
                            got = self.call(pdf["text"], pdf["ckpt"], pdf["draw"])
                            break
                        except (OSError, TimeoutError):
                            if not left:
                                raise
                            time.sleep(self.pause * 2 ** (self.retries - left))
                    yield pdf[["snippet_id", "ckpt", "draw"]].assign(q=got["q"].to_numpy(), s=got["s"].to_numpy())

        made = cells.select("snippet_id", "text", "ckpt", "draw").mapInPandas(run, "snippet_id long, ckpt int, draw int, q string, s string")
        return land(made)

    def train(self, samples: DataFrame, n_ckpt: int) -> EndpointSynthesizer:
        return self


@dataclass
class NGramSynthesizer:
    """A trainable bigram model: successors of each word with counts, per checkpoint.

    The vocabulary is capped by frequency (a size of the model, like a network's width), so the model that
    is sent to the tasks is bounded: vocab x fanout entries a checkpoint.  Drawing is Gumbel-max on
    ln p / temperature with seeded noise: the same cell always gives the same text.
    """

    vocab: int = 2000
    fanout: int = 16
    temperature: float = 0.2
    length: int = 40
    seed: int = 1
    models: list[dict[str, tuple[list[str], list[float]]]] = field(default_factory=list)
    counts: DataFrame | None = None

    def train(self, samples: DataFrame, n_ckpt: int = 3, text: str = "text", id_col: str = "id", prior: DataFrame | None = None) -> NGramSynthesizer:
        """Checkpoint m holds the prior counts and those of the first m / n_ckpt of the samples in hash order."""
        return trained([self], samples, n_ckpt, text, id_col, prior, prior is None)[0]

    def generate(self, snippets: DataFrame, ckpts: list[int], draws: int) -> DataFrame:
        """q: PASSAGE words from a hash-chosen place of the whole text; s goes on from one of them.

        A snippet's candidates are made in its own row, beside its `context_words` where it has them, so none is shuffled.
        """
        cells = [(c, d) for c in ckpts for d in range(draws)]
        own = [c for c in ("context_words",) if c in snippets.columns]
        if not cells:
            return snippets.select("snippet_id", F.lit(0).alias("ckpt"), F.lit(0).alias("draw"), F.lit("").alias("q"), F.lit("").alias("s"), *own).limit(0)
        out = self.nested(snippets, cells, own)
        which = F.array(*[F.struct(F.lit(c).alias("ckpt"), F.lit(k).alias("draw")) for c, k in cells]).alias("at")
        out = out.select("snippet_id", *own, F.explode(F.arrays_zip(which, "q", "s")).alias("_c"))
        return out.select("snippet_id", "_c.at.ckpt", "_c.at.draw", "_c.q", "_c.s", *own)

    def nested(self, snippets: DataFrame, cells: list[tuple[int, int]], own: list[str] = ["text"]) -> DataFrame:  # noqa: B006
        """(snippet_id, own columns, q, s): arrays of a snippet's candidates, one of each (ckpt, draw) in cells."""
        d = snippets.select("snippet_id", F.col("text").alias("_text"), texts.lowered("text").alias("_low"), *own)
        sent = snippets.sparkSession.sparkContext.broadcast([_Table.of(m, self.temperature) for m in self.models])
        seed, length = self.seed, self.length

        def passages(i: int, text: str | None, low: str | None) -> list[str]:
            w = [] if text is None else texts.split(text, low)
            last = max(1, len(w) - (PASSAGE - 1))
            starts = (texts.unit(f"passage{seed}", i, c, k) % last for c, k in cells)
            return [" ".join(w[x : x + PASSAGE]) for x in starts]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            tables = sent.value
            for batch in batches:
                ids, kept = batch.column("snippet_id").to_pylist(), [batch.column(c) for c in own]
                rows = list(zip(ids, batch.column("_text").to_pylist(), batch.column("_low").to_pylist()))
                asked, made = [], []
                for lo in range(0, len(ids), BLOCK):
                    part = [q for row in rows[lo : lo + BLOCK] for q in passages(*row)]
                    keys = [(i, c, k) for i in ids[lo : lo + BLOCK] for c, k in cells]
                    made += _written(tables, keys, part, seed, length)
                    asked += part
                at = pa.array(np.arange(0, len(made) + 1, len(cells)), pa.int32())
                q, s = (pa.ListArray.from_arrays(at, pa.array(x, pa.string())) for x in (asked, made))
                yield pa.RecordBatch.from_arrays([batch.column("snippet_id"), *kept, q, s], names=["snippet_id", *own, "q", "s"])

        kinds = {f.name: f.dataType.simpleString() for f in snippets.schema.fields}
        return d.mapInArrow(run, ", ".join(["snippet_id long", *(f"{c} {kinds[c]}" for c in own), "q array<string>", "s array<string>"]))


#: Snippets whose candidates are written at once.
BLOCK = 64


@dataclass
class _Table:
    """A checkpoint's model as arrays: log-weights, words and following contexts of each context; start: that of unknown words."""

    index: dict[str, int]
    start: int  # -1: none
    sizes: np.ndarray
    weight: np.ndarray
    words: np.ndarray
    follows: np.ndarray

    @classmethod
    def of(cls, model: dict[str, tuple[list[str], list[float]]], temperature: float) -> _Table:
        index = {u: k for k, u in enumerate(u for u, (w, _) in model.items() if w)}
        start, wide = index.get("<s>", -1), max((len(model[u][0]) for u in index), default=1)
        sizes = np.array([len(model[u][0]) for u in index], np.int64)
        weight, text, follows = np.full((len(index), wide), -np.inf), np.full((len(index), wide), "", object), np.full((len(index), wide), -1)
        for k, u in enumerate(index):
            w, c = model[u]
            weight[k, : len(w)], text[k, : len(w)], follows[k, : len(w)] = np.log(c) / temperature, w, [index.get(x, start) for x in w]
        return cls(index, start, sizes, weight, text, follows)


def _written(tables: list[_Table], keys: list[tuple[int, int, int]], passages: list[str], seed: int, length: int) -> list[str]:
    """The texts of (snippet, ckpt, draw) cells, word by word for all at once; each cell draws from its own seeded stream."""
    out = [""] * len(keys)
    model = np.array([min(c, len(tables) - 1) for _, c, _ in keys])
    for m in np.unique(model).tolist():
        t, rows = tables[m], np.flatnonzero(model == m)
        wide = t.weight.shape[1]
        noise, at = np.empty((len(rows), length * wide)), np.empty(len(rows), np.int64)
        for n, r in enumerate(rows.tolist()):
            i, c, k = keys[r]
            rng = np.random.default_rng([seed, int(i) & 0xFFFFFFFF, c, k])
            w = passages[r].split(" ") if passages[r] else []
            at[n] = t.index.get(w[int(rng.integers(len(w)))], t.start) if w else t.start
            rng.random(out=noise[n])
        noise = -np.log(-np.log(noise + 1e-12))
        used, columns = np.zeros(len(rows), np.int64), np.arange(wide)
        said = np.full((len(rows), length), "", object)
        going = np.flatnonzero(at >= 0)
        for step in range(length):
            if not len(going):
                break
            u = at[going]
            g = t.weight[u] + noise[going[:, None], np.minimum(used[going][:, None] + columns, noise.shape[1] - 1)]
            pick = np.where(columns < t.sizes[u][:, None], g, -np.inf).argmax(axis=1)  # a context of n words takes n numbers
            said[going, step], at[going] = t.words[u, pick], t.follows[u, pick]
            used[going] += t.sizes[u]
            going = going[at[going] >= 0]
        for r, s in zip(rows.tolist(), said.tolist()):
            out[r] = " ".join(w for w in s if w)
    return out


def pair_totals(samples: DataFrame, n_ckpt: int, text: str = "text", id_col: str = "id", prior: DataFrame | None = None) -> DataFrame:
    """(u, w, c0, c1, ...): counts of words after one another in the first of n_ckpt parts of the samples, the first two, ...;
    prior: landed (u, w, c) that all of them hold besides.

    Each task counts its own texts; a prior's pairs are not shuffled if the samples have few enough to be sent to them.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: list[Counter] = [Counter() for _ in range(n_ckpt)]

        def told() -> pa.RecordBatch:
            part = [m for m, c in enumerate(counts) for _ in range(len(c))]
            both = [p.split(" ") for c in counts for p in c]
            n = [k for c in counts for k in c.values()]
            for c in counts:
                c.clear()
            return pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array([x[0] for x in both], pa.string()), pa.array([x[1] for x in both], pa.string()), pa.array(n, pa.int64())], names=["part", "u", "w", "c"])

        for b in batches:
            for m, t, low in zip(*(b.column(c).to_pylist() for c in ("part", "text", "low"))):
                w = [] if t is None else texts.split(t, low)
                counts[m].update(map(" ".join, zip(["<s>", *w], w)))  # words hold no blank
                if sum(map(len, counts)) > texts.MOST_KNOWN:
                    yield told()
        yield told()

    part = (F.floor(hash_unit("ckpt", id_col) * n_ckpt / (1 << 32))).cast("int").alias("part")
    t = samples.select(part, F.col(text).alias("text"), texts.lowered(text).alias("low")).mapInArrow(run, "part int, u string, w string, c long")
    names = [f"c{m}" for m in range(n_ckpt)]
    own = t.groupBy("u", "w").agg(*[F.sum(F.when(F.col("part") <= m, F.col("c")).otherwise(0)).alias(c) for m, c in enumerate(names)])
    if prior is None:
        return own
    own = land(own)
    if own.count() > MOST_SENT:
        both = own.union(prior.select("u", "w", *[F.col("c").alias(c) for c in names]))
        return both.groupBy("u", "w").agg(*[F.sum(c).alias(c) for c in names])
    known = land(prior.join(F.broadcast(own.select("u", "w")), ["u", "w"], "left_semi").select("u", "w"))
    more = prior.join(F.broadcast(own), ["u", "w"], "left").select("u", "w", *[(F.col("c") + F.coalesce(c, F.lit(0))).alias(c) for c in names])
    return more.union(own.join(F.broadcast(known), ["u", "w"], "left_anti"))


def _contexts(c: DataFrame, n_ckpt: int, sizes: list[NGramSynthesizer]) -> DataFrame:
    """Landed (m, u): the contexts that may be among a model's `vocab` first ones at checkpoint m, and few others.

    A context's weight is the sum of its `fanout` largest counts: at most its whole count, and no less than its largest
    count and one for each further successor.  So a context whose whole count is below the vocab-th largest of those lower
    bounds is in no model, and its pairs needn't be ranked.
    """
    each = [F.struct(F.lit(m).alias("m"), F.sum(f"c{m}").alias("n"), F.max(f"c{m}").alias("top"), F.count(F.when(F.col(f"c{m}") > 0, 1)).alias("next")) for m in range(n_ckpt)]
    told = land(c.groupBy("u").agg(*[x.alias(f"_{m}") for m, x in enumerate(each)]).select("u", F.explode(F.array(*[f"_{m}" for m in range(n_ckpt)])).alias("x")).select("u", "x.*").filter("n > 0"))
    may = F.lit(False)
    for m in range(n_ckpt):
        for s in sizes:
            low = told.filter(F.col("m") == m).select((F.col("top") + F.least(F.lit(s.fanout), "next") - 1).alias("low"))
            first = low.orderBy(F.desc("low")).limit(s.vocab).agg(F.count(F.lit(1)), F.min("low")).first()
            may = may | ((F.col("m") == m) & (F.col("n") >= (first[1] if first[0] == s.vocab and s.vocab else 0)))
    return land(told.filter(may).select("m", "u"))


def trained(sizes: list[NGramSynthesizer], samples: DataFrame, n_ckpt: int = 3, text: str = "text", id_col: str = "id", prior: DataFrame | None = None, more: bool = True) -> list[NGramSynthesizer]:
    """Synthesizers of several sizes trained on the same samples: words are counted once, and one pass over the counts
    gives all checkpoints of all sizes.

    more: whether they are trained further; then the counts are landed, else worked out anew by who asks for them.
    """
    c = pair_totals(samples, n_ckpt, text, id_col, prior)
    c = land(c) if more else c
    upto = c.select("u", "w", F.posexplode(F.array(*[f"c{m}" for m in range(n_ckpt)])).alias("m", "c")).filter("c > 0")
    upto = join_sent(upto, _contexts(c, n_ckpt, sizes), ["m", "u"], "left_semi")
    k = F.row_number().over(Window.partitionBy("m", "u").orderBy(F.desc("c"), "w"))
    best = upto.withColumn("k", k).filter(F.col("k") <= max(s.fanout for s in sizes))
    n = [F.sum(F.when(F.col("k") <= s.fanout, F.col("c"))).alias(f"n{j}") for j, s in enumerate(sizes)]
    row = land(best.groupBy("m", "u").agg(*n, F.array_sort(F.collect_list(F.struct("k", "w", "c"))).alias("next")))
    out = []
    for j, s in enumerate(sizes):
        place = F.row_number().over(Window.partitionBy("m").orderBy(F.desc(f"n{j}"), "u"))
        top = row.select("m", "u", f"n{j}").withColumn("place", place).filter(F.col("place") <= s.vocab).select("m", "u")
        models: list[dict] = [{} for _ in range(n_ckpt)]
        for r in row.join(F.broadcast(top), ["m", "u"], "left_semi").select("m", "u", F.slice("next", 1, s.fanout).alias("next")).collect():
            models[r["m"]][r["u"]] = ([x["w"] for x in r["next"]], [float(x["c"]) for x in r["next"]])
        out.append(NGramSynthesizer(s.vocab, s.fanout, s.temperature, s.length, s.seed, models, c.select("u", "w", F.col(f"c{n_ckpt - 1}").alias("c"))))
    return out


def enhance(base: NGramSynthesizer, premium: DataFrame, n_ckpt: int = 3, text: str = "text", id_col: str = "id") -> NGramSynthesizer:
    """The original synthesizer trained on with the premium set."""
    return base.train(premium, n_ckpt, text, id_col, base.counts)


#: Prompts of earlier ways to make instructions, for any endpoint.
PROMPTS = {
    "bootstrap": "Write one new task unlike these: {tasks}",
    "depth": "Rewrite this task so that it needs one more step: {task}",
    "breadth": "Write a task of the same field but of another kind: {task}",
    "snippet": "Take this text as a start and write a problem with its solution: {snippet}",
}


def prompts(df: DataFrame, kind: str, column: str) -> DataFrame:
    """df with the prompt that a prior generator would send for `column`."""
    before, _, after = PROMPTS[kind].partition("{")
    return df.withColumn("prompt", F.concat(F.lit(before), F.col(column), F.lit(after.partition("}")[2])))


def novel(tasks: DataFrame, seen: DataFrame, column: str, id_col: str = "doc_id") -> DataFrame:
    """The novelty filter: of tasks with one normalised text the smallest id, unless the text was seen."""
    k = F.md5(normalise(column).cast("binary"))
    t = tasks.withColumn("_k", k)
    first = t.groupBy("_k").agg(F.min(id_col).alias(id_col))
    return t.join(first, ["_k", id_col], "left_semi").join(seen.select(k.alias("_k")), "_k", "left_anti").drop("_k")


def self_bootstrap(seeds: DataFrame, provider, rounds: int, width: int) -> DataFrame:
    """Seed-task bootstrapping: each round prompts with `width` tasks in hash order and keeps what is new.

    seeds: (snippet_id, text, n_chars); provider: a synthesizer; returns (snippet_id, text, round), the seeds as round 0.
    Tasks made in round t get ids t * 2^40 + the prompt's.
    """
    pool = land(seeds.select("snippet_id", "text", F.lit(0).alias("round")))
    for t in range(1, rounds + 1):
        asked = pool.orderBy(hash_unit(f"boot{t}", "snippet_id"), "snippet_id").limit(width)  # a heap of `width` a task
        asked = prompts(asked.withColumn("text", normalise("text")), "bootstrap", "text").select("snippet_id", F.col("prompt").alias("text"), F.length("prompt").cast("long").alias("n_chars"))
        made = provider.generate(asked, [0], 1).select((F.col("snippet_id") % (1 << 40) + t * (1 << 40)).alias("snippet_id"), F.col("s").alias("text"), F.lit(t).alias("round"))
        pool = land(pool.union(novel(made, pool, "text", "snippet_id")))
    return pool


def evolve(tasks: DataFrame, provider, mode: str = "depth") -> DataFrame:
    """Instruction evolution: (snippet_id, text, evolved) of every task rewritten once in depth or in breadth."""
    if mode not in ("depth", "breadth"):
        raise ValueError("tasks evolve in depth or in breadth")
    asked = prompts(tasks, mode, "text").select("snippet_id", F.col("prompt").alias("text"), F.length("prompt").cast("long").alias("n_chars"))
    return tasks.join(provider.generate(asked, [0], 1).select("snippet_id", F.col("s").alias("evolved")), "snippet_id").select("snippet_id", "text", "evolved")
