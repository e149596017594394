"""Multi-aspect marks of candidates and their folding into one score."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import five, fp, hash_unit, shingles, texts, words

MARKS = [f"x{k}" for k in range(1, 11)]
TARGET_LENGTH = 240
#: Stop words that tell the four languages of the tables apart.
STOP_WORDS = {"en": ["the", "of", "and", "that", "is"], "fr": ["le", "la", "les", "des", "une"], "de": ["der", "die", "das", "und", "ist"], "es": ["el", "los", "las", "que", "una"]}
SECRET = r"(password|secret|token|api_key)[ ]*[:=]|AKIA[A-Z0-9]{12}|[0-9a-f]{32}|[A-Za-z0-9._]+@[A-Za-z0-9]+[.][a-z]+"
_PUNCT = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


def punctuation(text: Column) -> Column:
    return F.length(text) - F.length(F.translate(text, _PUNCT, ""))


def _among(stop: list[str]) -> Callable[[Column], Column]:
    return lambda word: word.isin(stop)


def majority_language(tokens: Column) -> Column:
    """Index 0..3 of the language with most stop words, -1 where none stands out."""
    n = [F.size(F.filter(tokens, _among(ws))) for ws in STOP_WORDS.values()]
    top = F.greatest(*n)
    ties = sum((c == top).cast("int") for c in n)
    first = F.when(n[0] == top, 0).when(n[1] == top, 1).when(n[2] == top, 2).otherwise(3)
    return F.when((top == 0) | (ties > 1), -1).otherwise(first)


#: Benchmark runs that are sent to the tasks as a set, if they are so many at most (some 60 bytes each).
MOST_SENT = 1_000_000


def sent_runs(runs: DataFrame):
    """The runs (gram) as a broadcast set behind a check of their number, or the frame itself where they are too many."""
    if runs.limit(MOST_SENT + 1).count() > MOST_SENT:
        return runs
    return runs.sparkSession.sparkContext.broadcast(frozenset(r["gram"] for r in runs.select("gram").collect()))


def _sent(runs):
    """The broadcast set of runs; None for runs that weren't sent (then join)."""
    sent = sent_runs(runs) if isinstance(runs, DataFrame) else runs
    return None if isinstance(sent, DataFrame) else sent


def shared_runs(tokens: str, runs, n: int = 8):
    """A column: how many distinct runs of n words of the array column `tokens` are among `runs`; None for runs that
    weren't sent (then join).  runs: of sent_runs(), or a frame that is sent here."""
    sent = _sent(runs)
    if sent is None:
        return None

    @F.pandas_udf("int")
    def count(arrays: pd.Series) -> pd.Series:
        known = sent.value
        lists = (() if w is None else w.tolist() for w in arrays)
        return pd.Series([len(known.intersection(map(" ".join, zip(*(w[k:] for k in range(n)))))) for w in lists], dtype="int32")

    return count(tokens)


def has_runs(joined: str, sent, n: int = 8) -> Column:
    """Whether words joined by blanks hold a run of n words that is in the set of _sent(); a null holds none."""

    @F.pandas_udf("boolean")
    def look(texts: pd.Series) -> pd.Series:
        known = sent.value
        lists = (() if t is None else t.split(" ") for t in texts)
        return pd.Series([not known.isdisjoint(map(" ".join, zip(*(w[k:] for k in range(n))))) for w in lists], dtype="bool")

    return look(joined)


def with_context(snippets: DataFrame, text: str = "text") -> DataFrame:
    """snippets with their distinct words as `context_words`: split once, before the candidates fan out."""
    return snippets.withColumn("context_words", F.array_distinct(words(text)))


def rule_marks(df: DataFrame, leaks=None, context: str = "text", target: int = TARGET_LENGTH, strict: int = 20) -> DataFrame:
    """Add x1..x10, integer marks 1..5 by exact integer arithmetic.

    leaks: benchmark 8-word runs, a table (gram) or sent_runs() of it; without them x8 is 5.  The words of q and s are split once; those of
    the snippet are taken from `context_words` where with_context() made them.  target, strict: the length and the
    punctuation that the judge asks for.
    """
    own = F.col("context_words") if "context_words" in df.columns else words(context) if context in df.columns else words("s")
    df = df.withColumns({"_q": words("q"), "_s": words("s"), "_c": own})
    s = F.col("s")
    lines = F.split(s, "\n")
    both = F.size(F.array_intersect("_s", "_c"))
    lang_q, lang_s = majority_language(F.col("_q")), majority_language(F.col("_s"))
    sent = _sent(leaks) if leaks is not None else None
    marks = {
        "x1": five(F.size(F.array_intersect("_q", "_s")), F.size(F.array_distinct("_q"))),
        "x2": five(F.size(F.array_distinct("_s")), F.size("_s")),
        "x3": (5 - F.least(F.lit(4), F.floor(strict * punctuation(s) / F.greatest(F.lit(1), F.length(s))))).cast("int"),
        "x4": five(F.length(s), F.lit(target + 1)),
        "x5": five(F.size(F.array_distinct(lines)), F.size(lines)),
        "x6": (5 - F.least(F.lit(4), F.greatest(F.lit(0), F.floor(F.length(s) / F.greatest(F.lit(1), F.size("_s"))) - 7))).cast("int"),
        "x7": five(both, F.size(F.array_distinct("_s"))),
        "x8": F.lit(5),
        "x9": (5 - F.least(F.lit(4), 2 * F.regexp_count(s, F.lit(SECRET)))).cast("int"),
        "x10": F.when((lang_q == -1) | (lang_s == -1), 3).when(lang_q == lang_s, 5).otherwise(1).cast("int"),
    }
    # Python's input queue spills whole rows, so snippets and word lists end below it: `_w` is read twice above, which keeps
    # the optimizer from moving the marks over the queue.
    out = df.withColumns(marks).withColumn("_w", F.when(F.size("_s") >= 8, F.array_join("_s", " "))).drop("_q", "_s", "_c")
    if sent is not None:
        out = out.withColumn("x8", F.when(F.col("_w").isNotNull() & has_runs("_w", sent), 1).otherwise(5))
    out = out.drop("_w")
    if leaks is not None and sent is None:
        key = [c for c in ("snippet_id", "ckpt", "draw") if c in df.columns]
        grams = out.select(*key, words("s").alias("_t")).select(*key, F.explode(shingles(F.col("_t"), 8)).alias("gram"))
        hit = grams.join(leaks, "gram", "left_semi").select(*key).distinct().withColumn("_leak", F.lit(1))
        out = out.join(hit, key, "left").withColumn("x8", F.when(F.col("_leak").isNotNull(), 1).otherwise(5)).drop("_leak")
    return out


_SECRET_PATTERN = re.compile(SECRET)
_SECRET_WORDS = ("@", "AKIA", "password", "secret", "token", "api_key")
_HEX = bytes(104 if chr(k) in "0123456789abcdef" else 32 for k in range(256))


def secrets_in(text: str, raw: bytes) -> int:
    """Matches of SECRET; texts that hold none of its fixed parts are told without the pattern.  raw: the text's bytes."""
    if any(x in text for x in _SECRET_WORDS) or b"h" * 32 in raw.translate(_HEX):
        return sum(1 for _ in _SECRET_PATTERN.finditer(text))
    return 0


def without_punctuation(raw: bytes) -> bytes:
    return raw.translate(None, _PUNCT.encode())


_LANGUAGE = {w: k for k, ws in enumerate(STOP_WORDS.values()) for w in ws}


def _language(tokens: list[str]) -> int:
    found = [_LANGUAGE[w] for w in tokens if w in _LANGUAGE]
    n = [found.count(k) for k in range(len(STOP_WORDS))]
    return -1 if not found or n.count(max(n)) > 1 else n.index(max(n))


def marks_of(q: str | None, s: str | None, low_q: str | None, low_s: str | None, context: set[str] | None, known: texts.Runs | None, target: int = TARGET_LENGTH, strict: int = 20) -> tuple[int, ...]:
    """x1..x10 of rule_marks() for one candidate, in a worker; context: the snippet's words; known: the benchmark's runs;
    low_q, low_s: what texts.lowered() gave."""
    if s is None or q is None:  # of a null text: as the column functions have it
        return 5, 5, 1, 5, 5, 5, 5, 5, 1, 5
    wq, ws = texts.split(q, low_q), texts.split(s, low_s)
    dq, ds, lines, raw, n = set(wq), set(ws), s.split("\n"), s.encode(), max(1, len(s))
    mark = lambda part, whole: 1 + min(4, 5 * part // max(1, whole))
    a, b = _language(wq), _language(ws)
    return (
        mark(len(dq & ds), len(dq)),
        mark(len(ds), len(ws)),
        5 - min(4, strict * (len(raw) - len(without_punctuation(raw))) // n),
        mark(len(s), target + 1),
        mark(len(set(lines)), len(lines)),
        5 - min(4, max(0, len(s) // max(1, len(ws)) - 7)),
        5 if context is None else mark(len(ds & context), len(ds)),
        1 if known is not None and known.found(ws) else 5,
        5 - min(4, 2 * secrets_in(s, raw)),
        3 if -1 in (a, b) else 5 if a == b else 1,
    )


def with_lowered(cand: DataFrame, *own: str) -> DataFrame:
    """(own columns, text, _low, q, s, _lq, _ls) of rows with a text and arrays q and s, for read_cells()."""
    low = lambda c: F.when(F.exists(c, texts.is_odd), F.transform(c, F.lower))
    return cand.select(*own, "text", texts.lowered("text").alias("_low"), "q", "s", low("q").alias("_lq"), low("s").alias("_ls"))


def read_cells(batch: pa.RecordBatch, key: str) -> Iterator[tuple]:
    """(key, text, low, q, s, low_q, low_s) of each row in a worker, the last four being lists."""
    for k, text, low, q, s, lq, ls in zip(*(batch.column(c).to_pylist() for c in (key, "text", "_low", "q", "s", "_lq", "_ls"))):
        yield k, text, low, q, s, lq or [None] * len(q), ls or [None] * len(s)


def nested_marks(cand: DataFrame, own: list[str], leaks=None) -> DataFrame:
    """(own columns, x1, ..., x10) of each candidate in the arrays q and s beside their text: rule_marks() in one pass over a
    snippet.  leaks: a broadcast of sent_runs(), or None."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = texts.Runs(leaks.value) if leaks is not None else None
        for b in batches:
            at, marks = [], []
            for n, (_, text, low, *cells) in enumerate(read_cells(b, own[0])):
                context = set(texts.split(text, low)) if text is not None else None
                marks += [marks_of(*x, context, known) for x in zip(*cells)]
                at += [n] * len(cells[0])
            m = np.array(marks, np.int32).reshape(-1, len(MARKS))
            at = pa.array(at, pa.int64())
            yield pa.RecordBatch.from_arrays([*(b.column(c).take(at) for c in own), *(pa.array(m[:, k]) for k in range(len(MARKS)))], names=[*own, *MARKS])

    return with_lowered(cand, *own).mapInArrow(run, T.StructType([*(cand.schema[c] for c in own), *(T.StructField(x, T.IntegerType()) for x in MARKS)]))


def callable_marks(df: DataFrame, judge: Callable[[pd.Series, pd.Series], pd.DataFrame], z: int) -> DataFrame:
    """Marks x1..xz from any judge of (q, s) batches, for instance a served model."""
    schema = ", ".join(f"x{k + 1} int" for k in range(z))

    @F.pandas_udf(schema)
    def run(q: pd.Series, s: pd.Series) -> pd.DataFrame:
        return judge(q, s)

    return df.withColumn("_m", run("q", "s")).select("*", "_m.*").drop("_m")


def weighted(df: DataFrame, w: list[float], marks: list[str] = MARKS, out: str = "score") -> DataFrame:
    """Sum of weight x mark: literals and columns only, so it stays in generated code."""
    total = F.lit(0.0)
    for k, name in zip(w, marks):
        total = total + F.lit(float(k)) * F.col(name)
    return df.withColumn(out, total).withColumn(f"{out}_fp", fp(F.col(out)))


def simple_average(df: DataFrame, marks: list[str] = MARKS, out: str = "score") -> DataFrame:
    return df.withColumn(out, sum(F.col(m) for m in marks) / F.lit(float(len(marks)))).withColumn(f"{out}_fp", fp(F.col(out)))


def composite(df: DataFrame, marks: list[str] = MARKS, out: str = "score") -> DataFrame:
    """One overall mark 1..5: coarse and full of ties."""
    z = len(marks)
    return df.withColumn(out, (1 + F.least(F.lit(4), F.floor(sum(F.col(m) - 1 for m in marks) / z))).cast("int"))


def none(df: DataFrame, seed: str = "none", out: str = "score") -> DataFrame:
    """The ablation: a hash of the candidate in place of a score."""
    return df.withColumn(out, hash_unit(seed, "snippet_id", "ckpt", "draw"))
