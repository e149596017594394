"""The self-distillation loop: sample, mark and pick, rank by influence, keep, train, round after round.

A reference model is trained once on the premium set: a low-rank adapter on a frozen base.  Every kept-to-be sample's
adapter gradient is projected inside its task and compared with the premium set's mean.  Rounds meet through files only
(landed tables and a manifest), so a lost driver goes on from the last whole round and no plan grows with the rounds.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import UNIT, hash_unit, texts, words
from ..operators import candidates, influence, lm, reference, scoring, selection
from ..sources import exists, join_sent, land, scratch

#: Rounds as multiples of the premium size.
SCHEDULES = {"20-40": (2, 4), "60": (6,), "40-20": (4, 2), "40-40": (4, 4), "20-20": (2, 2)}
LEDGER = "iteration int, stage string, provider string, calls long, kept long, prompt_chars long, output_chars long"


@dataclass(frozen=True)
class Config:
    schedule: str = "20-40"
    unit: int = 10
    ckpts: int = 3
    draws: int = 4
    weights: tuple[float, ...] = (1.0, 1.0, 2.0, 1.0, 1.0, 1.0, 1.0, 1.0, 1.0, 1.0)
    aggregate: str = "weighted"  # weighted, average, composite, none
    sampling: str = "multi"  # multi, last, best_of_n
    final: str = "influence"  # influence, random, score, low_ppl, high_ppl
    over: int = 2  # prompted snippets per kept one
    disjoint: bool = True  # a snippet that was prompted once is not prompted again
    include_seed: bool = False
    restart: bool = False  # train each round from the synthesizer of round 0, on all kept so far
    rounds: int | None = None  # at most so many
    stall: float | None = None  # stop when the proxy gains less than this over a round
    reference: str = "trained"  # trained, fixed (checkable by any engine), words (shares of hashed words)
    vocabulary: int = 64  # hashed words of the reference
    rank: int = 4
    width: int = 64  # of the projection
    loss_on: str = "solution"


@dataclass
class Result:
    rounds: list[DataFrame] = field(default_factory=list)
    ledger: list[tuple] = field(default_factory=list)
    synths: list = field(default_factory=list)
    proxies: list[float] = field(default_factory=list)


def sizes(cfg: Config) -> list[int]:
    return [m * cfg.unit for m in SCHEDULES[cfg.schedule]][: cfg.rounds]


def unit_of(pool_rows: int) -> int:
    """The largest premium size for which every schedule fits a pool of so many snippets, two prompted for each kept."""
    unit = pool_rows // 18
    if not unit:
        raise ValueError(f"a pool of {pool_rows} snippets is too small for one round of every schedule")
    return unit


def word_vectors(df: DataFrame, id_col: str, text: str, width: int) -> DataFrame:
    """(id, g): hashed word shares in millionths, negated: the gradient of a unigram model without its base."""
    ids = reference.word_ids(words(text), width, "")
    return df.select(F.col(id_col).alias("id"), F.transform(reference.shares(ids, width), lambda x: -x).alias("g"))


@dataclass
class Reference:
    """The reference model of a run: gradients of (q, s) rows, and the premium set's summed gradient."""

    model: reference.LowRankBigram | None
    signs: np.ndarray | None
    target: list[int]
    cfg: Config

    @classmethod
    def make(cls, pool: DataFrame, premium: DataFrame, cfg: Config) -> Reference:
        """Base from the pool's texts, adapters from the premium set (id, q, s)."""
        if cfg.reference == "words":
            ref = cls(None, None, [], cfg)
        else:
            v = cfg.vocabulary
            base = reference.text_pair_counts(pool, "text", v)
            if cfg.reference == "fixed":
                model = reference.LowRankBigram.fixed(base, cfg.rank)
                signs = influence.signs("proj", model.width, cfg.width)
            else:
                own = reference.pair_counts(reference.pair_codes(premium, "id", "s", v, "q", cfg.loss_on), v)
                model = reference.LowRankBigram.start(base, cfg.rank).fit(own)
                signs = influence.fast_signs(zlib.crc32(b"proj"), 0, model.width, cfg.width).astype(np.int64)
            ref = cls(model, signs, [], cfg)
        ref.target = influence.target_sum(ref.gradients(premium, "id"))
        return ref

    def gradients(self, df: DataFrame, id_col: str) -> DataFrame:
        if self.model is None:
            return word_vectors(df, id_col, "s", self.cfg.width)
        pairs = reference.pair_codes(df, id_col, "s", len(self.model.b), "q", self.cfg.loss_on)
        return self.model.per_sample(pairs, self.signs, per_word=self.cfg.reference == "trained")


    def in_worker(self) -> Callable[[], Callable[[str | None, ...], float | None]]:
        """A maker of functions from (q, s, low_q, low_s) to the influence of ref_scores(), for workers; the table is sent."""
        sent = SparkSession.active().sparkContext.broadcast(self.model.table(self.signs))  # V * V * k numbers, sizes of the model
        v, per_word, loss_on, target = len(self.model.b), self.cfg.reference == "trained", self.cfg.loss_on, self.target

        def make() -> Callable[[str | None, ...], float | None]:
            table, ids, cosine = sent.value, texts.Ids(v), influence.Cosine(target)

            def told(q: str | None, s: str | None, low_q: str | None, low_s: str | None) -> float | None:
                c = reference.codes_of(ids, s, low_s, q, low_q, loss_on)
                g = table[c].sum(axis=0)
                return cosine(np.rint(g / max(1, len(c))) if per_word else g)

            return told

        return make


def prompted(snippets: DataFrame, n: int, t: int) -> DataFrame:
    """n snippets in the hash order of the round; only ids are ranked."""
    return join_sent(snippets, land(selection.random_n(snippets.select("snippet_id"), n, f"round{t}", "snippet_id")), "snippet_id", "left_semi")


def _cells(cfg: Config) -> list[tuple[int, int]]:
    """(ckpt, draw) of a snippet's candidates."""
    if cfg.sampling == "multi":
        return [(c, d) for c in range(cfg.ckpts) for d in range(cfg.draws)]
    return [(cfg.ckpts - 1, d) for d in range(cfg.draws if cfg.sampling == "best_of_n" else cfg.ckpts * cfg.draws)]


def sampled(prompts: DataFrame, cfg: Config, synth=None) -> DataFrame:
    """The candidates of the prompted snippets, by the configured sampling."""
    prompts = scoring.with_context(prompts)
    gen = synth.generate if synth is not None else (lambda s, c, d: candidates.passages(candidates.grid(s, c, d)))
    if cfg.sampling == "last":
        cand = gen(prompts, [cfg.ckpts - 1], cfg.ckpts * cfg.draws)
    elif cfg.sampling == "best_of_n":
        cand = gen(prompts, [cfg.ckpts - 1], cfg.draws)
    else:
        cand = gen(prompts, list(range(cfg.ckpts)), cfg.draws)
    if "context_words" not in cand.columns:  # a model's rows: made once, then marked beside their snippets
        cand = land(cand).join(prompts.select("snippet_id", "context_words"), "snippet_id")
    return cand


def _folded(marked: DataFrame, cfg: Config) -> tuple[DataFrame, str]:
    """Marked candidates with their score, and the column that they are picked by."""
    fold = {"weighted": lambda d: scoring.weighted(d, list(cfg.weights)), "average": scoring.simple_average, "composite": scoring.composite, "none": scoring.none}
    return fold[cfg.aggregate](marked), "score" if cfg.aggregate in ("composite", "none") else "score_fp"


def picked(cand: DataFrame, cfg: Config, leaks=None) -> DataFrame:
    """(snippet_id, ckpt, draw, score, q, s, calls, chars): the best candidate of each snippet, ties by checkpoint and
    draw, landed; calls, chars: of all its candidates.  Each task reduces its snippets to one row before the shuffle."""
    scored, by = _folded(cand if cfg.aggregate == "none" else scoring.rule_marks(cand, leaks), cfg)
    g = scored.groupBy("snippet_id").agg(F.max(_rank(by)).alias("b"), F.count(F.lit(1)).alias("calls"), F.sum(_chars()).cast("long").alias("chars"))
    return land(g.select("snippet_id", *_winner("b"), "calls", "chars"))


def _chars() -> Column:
    return F.length("q") + F.length("s")


def _rank(by: str) -> Column:
    return F.struct(F.col(by).cast("long").alias("score"), (-F.col("ckpt")).alias("c"), (-F.col("draw")).alias("d"), "q", "s")


def _winner(b: str) -> list[Column]:
    return [(-F.col(f"{b}.c")).alias("ckpt"), (-F.col(f"{b}.d")).alias("draw"), F.col(f"{b}.score"), F.col(f"{b}.q"), F.col(f"{b}.s")]


def rule(cfg: Config) -> tuple[str, str]:
    """What a snippet's winner depends on, besides the snippet."""
    return cfg.sampling, cfg.aggregate


def nested(prompts: DataFrame, cells: list[tuple[int, int]], synth=None) -> DataFrame | None:
    """(snippet_id, text, q, s): each snippet's candidates in its own row, in the order of cells; None for providers whose
    candidates are rows of their own."""
    if synth is not None:
        return synth.nested(prompts, cells) if hasattr(synth, "nested") else None
    return candidates.placed(prompts, cells).select("snippet_id", "text", "q", "s")


def _by_rule(marks: np.ndarray, cfg: Config, hashes: Callable[[], np.ndarray]) -> np.ndarray:
    """What candidates are picked by, as _folded() has it; marks: (candidates, marks); hashes: of the candidates."""
    if cfg.aggregate == "none":
        return hashes()
    if cfg.aggregate == "composite":
        return 1 + np.minimum(4, (marks - 1).sum(axis=1) // marks.shape[1])
    if cfg.aggregate == "average":
        total = marks.sum(axis=1) / float(marks.shape[1])
    else:
        total = np.zeros(len(marks))
        for k, w in enumerate(cfg.weights):
            total = total + float(w) * marks[:, k]
    x = total * float(UNIT)
    whole = np.floor(np.abs(x))
    return (np.sign(x) * (whole + (np.abs(x) - whole >= 0.5))).astype(np.int64)


def winners(cand: DataFrame, cells: list[tuple[int, int]], cfgs: list[Config], leaks=None, ref: Reference | None = None) -> DataFrame:
    """(snippet_id, b0, b1, ...): the winner of each cfg's rule among the candidates of nested(), picked as picked() does,
    and with a reference model its influence v.  A snippet is marked, picked and ranked in its own row: nothing is shuffled.

    cells: in ascending order; leaks: a broadcast of sent_runs(), or None.
    """
    own = [sorted(cells.index(x) for x in _cells(c)) for c in cfgs]
    make = ref.in_worker() if ref is not None and ref.model is not None else None
    kind = pa.struct([("ckpt", pa.int32()), ("draw", pa.int32()), ("score", pa.int64()), ("q", pa.string()), ("s", pa.string()), ("calls", pa.int64()), ("chars", pa.int64()), ("v", pa.float64())])
    marked = any(c.aggregate != "none" for c in cfgs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, influence_of = texts.Runs(leaks.value) if leaks is not None else None, make() if make else None
        for b in batches:
            out: list[list[dict]] = [[] for _ in cfgs]
            for i, text, low, qs, ss, lqs, lss in scoring.read_cells(b, "snippet_id"):
                context = set(texts.split(text, low)) if text is not None and marked else None
                m = np.array([scoring.marks_of(*x, context, known) for x in zip(qs, ss, lqs, lss)], np.int64) if marked else None
                hashes = lambda i=i: np.array([texts.unit("none", i, c, d) for c, d in cells])
                seen: dict[int, float | None] = {}
                for k, (c, mine) in enumerate(zip(cfgs, own)):
                    score = _by_rule(m, c, hashes)[mine]
                    n = mine[int(score.argmax())]
                    if influence_of and n not in seen:
                        seen[n] = influence_of(qs[n], ss[n], lqs[n], lss[n])
                    chars = [len(qs[x]) + len(ss[x]) for x in mine if qs[x] is not None and ss[x] is not None]
                    out[k].append({"ckpt": cells[n][0], "draw": cells[n][1], "score": int(score.max()), "q": qs[n], "s": ss[n], "calls": len(mine), "chars": sum(chars) if chars else None, "v": seen.get(n)})
            yield pa.RecordBatch.from_arrays([b.column("snippet_id"), *(pa.array(x, kind) for x in out)], names=["snippet_id", *(f"b{k}" for k in range(len(cfgs)))])

    struct = "struct<ckpt int, draw int, score long, q string, s string, calls long, chars long, v double>"
    return scoring.with_lowered(cand, "snippet_id").mapInArrow(run, ", ".join(["snippet_id long", *(f"b{k} {struct}" for k in range(len(cfgs)))]))


def _flat(best: DataFrame, k: int, ref: Reference | None) -> DataFrame:
    """picked() of the k-th rule from landed winners(), with v and v_fp where a reference is given."""
    won = best.select("snippet_id", *[f"b{k}.{c}" for c in ("ckpt", "draw", "score", "q", "s", "calls", "chars")], *([F.col(f"b{k}.v").alias("v")] if ref is not None and ref.model is not None else []))
    if ref is None:
        return won
    if ref.model is None:
        return land(won.join(ref_scores(won, ref), "snippet_id"))
    return won.withColumn("v_fp", F.round(F.col("v") * UNIT).cast("long"))


def _sent(leaks):
    """(whether leaks can be told in workers, their broadcast)."""
    if isinstance(leaks, DataFrame):
        leaks = scoring.sent_runs(leaks)
    return not isinstance(leaks, DataFrame), leaks


def best_of(prompts: DataFrame, cfg: Config, synth=None, leaks=None, ref: Reference | None = None) -> DataFrame:
    """picked() of sampled(), and with a reference the influence too; in the snippets' rows wherever the provider allows."""
    cells = sorted(_cells(cfg))
    told, sent = _sent(leaks)
    cand = nested(prompts, cells, synth) if told and cells else None
    if cand is None:
        return picked(sampled(prompts, cfg, synth), cfg, sent)
    return _flat(land(winners(cand, cells, [cfg], sent, ref)), 0, ref)


def prepared(prompts: DataFrame, cfgs: list[Config], ref: Reference, leaks=None) -> dict[tuple[str, str], DataFrame]:
    """picked() of hash-placed candidates with their influence, by every rule among cfgs, which else are alike.

    A hash-placed candidate depends on its snippet alone, not on the round or the run, so each is made and marked once.
    """
    rules = {rule(c): c for c in cfgs}
    told, sent = _sent(leaks)
    if not told:
        return {name: (lambda won: land(won.join(ref_scores(won, ref), "snippet_id")))(picked(sampled(prompts, c), c, sent)) for name, c in rules.items()}
    cells = sorted({x for c in rules.values() for x in _cells(c)})
    best = land(winners(nested(prompts, cells), cells, list(rules.values()), sent, ref))
    return {name: _flat(best, k, ref) for k, name in enumerate(rules)}


def ranked(best: DataFrame, keep: int, cfg: Config, t: int, ref: Reference, pool_lm: lm.NGram | None = None) -> DataFrame:
    """The kept rows of picked(), with their influence v and v_fp; those of prepared() have it."""
    joined = best if "v_fp" in best.columns else best.join(ref_scores(best, ref), "snippet_id")
    if cfg.final == "random":
        return selection.random_n(joined, keep, f"keep{t}", "snippet_id")
    if cfg.final == "score":
        return selection.top_n(joined, "score", keep, "snippet_id")
    if cfg.final in ("low_ppl", "high_ppl"):
        p = lm.perplexity(best, "snippet_id", "s", pool_lm).select(F.col("id").alias("snippet_id"), "ppl")
        return selection.top_n(joined.join(p, "snippet_id"), "ppl", keep, "snippet_id", ascending=cfg.final == "low_ppl").drop("ppl")
    return selection.top_n(joined, "v_fp", keep, "snippet_id")


def ref_scores(best: DataFrame, ref: Reference) -> DataFrame:
    """(snippet_id, v, v_fp) of rows with q and s."""
    return influence.score(ref.gradients(best, "snippet_id"), ref.target).withColumnRenamed("id", "snippet_id")


def one_round(snippets: DataFrame, keep: int, cfg: Config, t: int, ref: Reference, synth=None, leaks=None, pool_lm: lm.NGram | None = None, ready: DataFrame | None = None) -> DataFrame:
    """(iteration, snippet_id, ckpt, draw, score, v, q, s): the kept samples of one round; leaks: (gram) of the benchmark;
    ready: prepared() rows of the round's prompts, and of no other snippet."""
    best = best_of(prompted(snippets, keep * cfg.over, t), cfg, synth, leaks, ref) if ready is None else ready
    kept = ranked(best, keep, cfg, t, ref, pool_lm)
    return kept.select(F.lit(t).alias("iteration"), "snippet_id", "ckpt", "draw", "score", "v", "q", "s")


def told_of(pool: DataFrame, premium: DataFrame) -> tuple[list, list]:
    """Number and digest of the ids and texts of a pool and its premium set: read once for all runs that share them."""
    one = lambda df, k: list(df.agg(F.count(F.lit(1)), F.sum(F.xxhash64(k, "text" if "text" in df.columns else "s").cast("decimal(38,0)"))).first())
    return one(pool, "snippet_id"), one(premium, "id")


def _digest(cfg: Config, rows: list, premium: list, synth) -> str:
    """Of the settings and of the ids and texts that a run works on."""
    told = {"cfg": asdict(cfg), "pool": [str(x) for x in rows], "premium": [str(x) for x in premium], "synth": type(synth).__name__}
    return json.dumps(told, sort_keys=True)


def run(pool: DataFrame, premium: DataFrame, cfg: Config = Config(), synth=None, path: str | None = None, leaks=None, proxy=None, ref: Reference | None = None, ready: DataFrame | None = None, asked: list[DataFrame] | None = None, pool_lm: lm.NGram | None = None, told: tuple[list, list] | None = None) -> Result:
    """pool: (snippet_id, text, n_chars), without the premium snippets; premium: (id, q, s) and, for the
    ledger, asked: characters of the snippet it was made from; leaks: (gram) of the benchmark.

    Round t is sampled from the synthesizer of round t - 1 (`synth`: that of round 0, none for hash-placed passages).  A
    round whose manifest exists is read, not made; a manifest of other settings or other data is refused.  proxy: a
    function of a round's kept rows to a number that should fall; with cfg.stall the loop stops when it no longer does.
    ready: prepared() rows of all snippets that may be prompted; asked: prompts_of() a run of the same pool and schedule;
    told: told_of() the pool and the premium set.
    """
    spark: SparkSession = pool.sparkSession
    path = path or scratch(spark)
    plan = sizes(cfg)
    need = sum(k * cfg.over for k in plan) if cfg.disjoint else max(k * cfg.over for k in plan)
    rows = told or told_of(pool, premium)
    digest, have = _digest(cfg, *rows, synth), rows[0][0]
    if have < need:
        raise ValueError(f"the schedule needs {need} snippets, the pool has {have}")
    ref = ref or Reference.make(pool, premium, cfg)
    if pool_lm is None and cfg.final in ("low_ppl", "high_ppl"):
        pool_lm = lm.fit(pool, "snippet_id", "text")
    n, chars, before = premium.agg(F.count(F.lit(1)), F.sum(F.length("q") + F.length("s")), F.sum("asked" if "asked" in premium.columns else F.lit(0))).first()
    out = Result(ledger=[(0, "distill", "premium", n, n, int(before or 0), int(chars or 0))], synths=[synth])
    used, start = None, synth
    for t, keep in enumerate(plan, 1):
        here = f"{path}/round={t}"
        if exists(spark, f"{here}/manifest"):
            done = json.loads(spark.read.text(f"{here}/manifest").first()[0])
            if done["digest"] != digest:
                raise ValueError(f"{here} was made with other settings or data")
            kept, prompts = spark.read.parquet(f"{here}/samples"), spark.read.parquet(f"{here}/prompts")
        else:
            prompts = land(_next(pool, used, keep, cfg, t) if asked is None else asked[t - 1], f"{here}/prompts")
            if ready is None:
                best = best_of(join_sent(pool, prompts.select("snippet_id"), "snippet_id", "left_semi"), cfg, synth, leaks, ref)
            else:
                best = join_sent(ready, prompts.select("snippet_id"), "snippet_id", "left_semi")
            calls, chars, told_chars = join_sent(best, prompts.withColumnRenamed("chars", "_asked"), "snippet_id", "inner").agg(F.sum("calls"), F.sum("chars"), F.sum(F.col("calls") * F.col("_asked"))).first()
            kept = ranked(best, keep, cfg, t, ref, pool_lm)
            kept = land(kept.select(F.lit(t).alias("iteration"), "snippet_id", "ckpt", "draw", "score", "v", "q", "s"), f"{here}/samples")
            done = {"digest": digest, "kept": kept.count(), "calls": int(calls or 0), "prompt_chars": int(told_chars or 0), "output_chars": int(chars or 0)}
            spark.createDataFrame([(json.dumps(done),)], "value string").coalesce(1).write.mode("overwrite").text(f"{here}/manifest")
        out.ledger.append((t, "sample", "self", done["calls"], done["kept"], done["prompt_chars"], done["output_chars"]))
        ids = prompts.select("snippet_id")
        used = ids if used is None else used.union(ids)
        out.rounds.append(kept)
        if synth is not None:
            rows = kept if not cfg.restart else _all(out.rounds)
            train = rows.select(F.col("snippet_id").alias("id"), F.col("s").alias("text"))
            if cfg.include_seed:
                train = train.union(premium.select("id", F.col("s").alias("text")))
            synth = (start if cfg.restart else synth).train(train, cfg.ckpts)
        out.synths.append(synth)
        if proxy is not None:
            out.proxies.append(proxy(kept))
            if cfg.stall is not None and len(out.proxies) > 1 and out.proxies[-2] - out.proxies[-1] < cfg.stall:
                break
    return out


def _next(pool: DataFrame, used: DataFrame | None, keep: int, cfg: Config, t: int) -> DataFrame:
    """(snippet_id, chars) of the snippets that round t prompts; used: those of the rounds before."""
    ids = pool.select("snippet_id", F.length("text").alias("chars"))
    fresh = ids if used is None or not cfg.disjoint else join_sent(ids, used, "snippet_id", "left_anti")
    return selection.random_n(fresh, keep * cfg.over, f"round{t}", "snippet_id")


def prompts_of(pool: DataFrame, cfg: Config) -> list[DataFrame]:
    """The prompts of each round of a run: they depend on the pool, the schedule and `over` alone."""
    out: list[DataFrame] = []
    for t, keep in enumerate(sizes(cfg), 1):
        used = _all([p.select("snippet_id") for p in out]) if out else None
        out.append(land(_next(pool, used, keep, cfg, t)))
    return out


def _all(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def final_dataset(synth, snippets: DataFrame, n: int, cfg: Config, ref: Reference | None = None, leaks=None, filtered: bool = False, asked: DataFrame | None = None) -> DataFrame:
    """(snippet_id, q, s): the training set of a target model, n samples of the last synthesizer.

    One draw of the last checkpoint for each of n snippets in hash order; filtered: as many are sampled, marked and
    ranked as in a round.  asked: the prompted snippets, where several synthesizers share them.
    """
    if filtered:
        return one_round(snippets, n, cfg, 99, ref, synth, leaks).select("snippet_id", "q", "s")
    asked = prompted(snippets, n, 99) if asked is None else asked
    made = candidates.passages(candidates.grid(asked, [cfg.ckpts - 1], 1)) if synth is None else synth.generate(asked, [cfg.ckpts - 1], 1)
    return made.select("snippet_id", "q", "s")


ABLATIONS = {
    "full": {}, "no_multi_ckpt": {"sampling": "last"}, "no_scoring": {"aggregate": "none"}, "no_influence": {"final": "random"},
    "average": {"aggregate": "average"}, "composite": {"aggregate": "composite"}, "best_of_n": {"sampling": "best_of_n"}, "best_score": {"final": "score"},
}
#: What the selection strategies are compared by: the folding of marks, then the last selection.
STRATEGIES = {
    "full": {}, "composite": {"aggregate": "composite"}, "average": {"aggregate": "average"},
    "random": {"final": "random"}, "low_ppl": {"final": "low_ppl"}, "high_ppl": {"final": "high_ppl"},
}
