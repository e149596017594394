"""Secret scans: fixed patterns, and two character Markov models compared by log-likelihood ratio.

One model is trained on random strings, the other on ordinary identifiers.  The samples are labelled
by the pattern rules over all documents (values inside a match of a rule are random strings, all other
text is ordinary, but for the tokens that are to be judged), with seeded draws over the usual alphabets and seeded
compound identifiers so that neither model is ever empty.  What training gathers is one count per character pair and
label.  Every token of LEAST_TOKEN characters or more outside the rules' matches is judged, by the ratio alone: the
threshold is the one that separates held-out samples of both labels best, a false alarm counting as ALARM misses.
"""

from __future__ import annotations

import bisect
import hashlib
import itertools
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Fixed values of the contract.
ASSIGN = re.compile(r"""(?ai:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]{12,}")
HEX = re.compile(r"[0-9a-f]{32,}")
KINDS = ("assign", "access", "hex", "markov")
LEAST_VALUE = 8
_WORDS = ("passw", "secret", "token", "key")

TOKEN = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
WORD = re.compile(r"[A-Za-z0-9+/_=-]{4,}")
CHARS = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
LEAST_TOKEN = 16
#: Thresholds of the mean log-likelihood ratio per character (nats) that are tried.
RATIOS = [k / 20 for k in range(10, 51)]
#: Misses that weigh as much as one false alarm.
ALARM = 10
#: Weight, in characters, of a model's plain frequencies against its pair counts.
BACKING = 5.0
DRAWS = 2000
SEED = 11
#: What the seeded identifiers are made of.
PARTS = """account action add address all allow append apply argument array async attribute audio back base batch begin binary block body buffer build byte cache call
change channel char check child class clean clear client close code collection color column command commit compile compress config connect constant container content context
control convert copy count create current cursor data date debug decode default delete dependency describe detail device dict directory disable display document domain download
drop dump edit element email enable encode end entry environment error event exception execute exit export extension extract failure feature field file filter find first flag
flush format forward frame function generate get global graph group handle hash header height help hidden history hook host icon identifier image import index info init input
insert instance integer interface internal invalid item iterator job join key kind label language last layout length level library limit line link list load local lock log
login loop main make manager map mask master match max memory menu merge message method min mode model module move name namespace network new next node notify null number object
offset open operation option order origin output owner package page parameter parent parse partial password path pattern pending permission pipeline platform plugin point pool
port position prefix prepare previous print priority private process product profile project property protocol provider proxy public push query queue random range rate raw read
record recursive reference refresh register release remote remove rename render replace report request require reset resolve resource response rest result resume return role root
route row run sample save scale schedule schema scope screen script search section secret select send sequence server service session set setting setup shape shared shift shutdown
signal simple size skip socket sort source split stack stage start state static status step stop storage store stream string struct style submit suffix summary support switch
symbol sync system table tag target task template temp test text thread time timeout title token tool total trace track transaction transform tree trigger type unique unit
unknown update upload user util valid validate value variable vector verify version video view visible wait warning watch web weight width window word work worker wrap write zone""".split()

Span = tuple[int, int, int]  # start, kind, end


def base_spans(text: str) -> list[Span]:
    """Matches of the three fixed patterns, each kind leftmost and non-overlapping; code points."""
    found = []
    low = text.lower()
    if any(word in low for word in _WORDS):  # no keyword, no match: spares most texts the slow pattern
        found = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= LEAST_VALUE]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text)]
    if b"1" * 32 in text.encode("utf-8", "surrogatepass").translate(_IS_HEX):
        found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def _outside(tokens: Iterator[re.Match], spans: list[Span]) -> Iterator[re.Match]:
    """The tokens that touch none of the sorted spans; the spans of several kinds may overlap."""
    starts = [s for s, _, _ in spans]
    reach = list(itertools.accumulate((e for _, _, e in spans), max))
    for m in tokens:
        before = bisect.bisect_left(starts, m.end())
        if not before or reach[before - 1] <= m.start():
            yield m


_AT = {c: i + 1 for i, c in enumerate(CHARS)}
_N = len(CHARS) + 1  # 0: before the first character


_CLASS = np.zeros(256, np.int64)
for _c, _k in _AT.items():
    _CLASS[ord(_c)] = _k
_IS_HEX = bytes(49 if chr(c) in "0123456789abcdef" else 48 for c in range(256))
_IS_TOKEN = bytes(49 if chr(c) in CHARS else 48 for c in range(256))


def _pairs(data: bytes) -> np.ndarray:
    """Counts of (character, next character) where the next one is of CHARS; 0 stands for all others."""
    k = _CLASS[np.frombuffer(b" " + data, np.uint8)]
    code = k[:-1] * _N + k[1:]
    return np.bincount(code[k[1:] > 0], minlength=_N * _N)


def random_samples(n: int = DRAWS, seed: int = SEED) -> list[str]:
    """Seeded random strings over hexadecimal, upper-case, alphanumeric and base64 alphabets."""
    rng = np.random.default_rng(seed)
    alphabets = ["0123456789abcdef", CHARS[:26] + CHARS[52:62], CHARS[:62], CHARS[:64], CHARS[:62] + "_-"]
    return ["".join(rng.choice(list(alphabets[k % len(alphabets)]), int(rng.integers(16, 65)))) for k in range(n)]


def ordinary_samples(n: int = DRAWS, seed: int = SEED) -> list[str]:
    """Seeded compound identifiers in the usual spellings, some with versions or numbers, dates, paths, plain numbers."""
    rng = np.random.default_rng(seed)
    out = []
    for k in range(n):
        w = [PARTS[i] for i in rng.integers(len(PARTS), size=int(rng.integers(2, 6)))]
        if rng.random() < 0.3:
            w[int(rng.integers(len(w)))] += str(rng.integers(100))
        if rng.random() < 0.15:
            w.append(f"v{rng.integers(1, 30)}")
        y, m, d, t = int(rng.integers(1970, 2040)), int(rng.integers(1, 13)), int(rng.integers(1, 29)), int(rng.integers(0, 86400))
        clock = f"{t // 3600:02d}{t // 60 % 60:02d}{t % 60:02d}"
        camel = "".join(x.capitalize() for x in w)
        styles = (
            "_".join(w), "_".join(w).upper(), camel, camel[0].lower() + camel[1:], "-".join(w), "/" + "/".join(w), "__" + "_".join(w), "=" * 8 + "-" * 8, str(rng.integers(10**15, 10**18)),
            f"{w[0].upper()}_{y}{m:02d}{d:02d}_{clock}", f"{y}-{m:02d}-{d:02d}T{clock[:2]}-{clock[2:4]}-{clock[4:]}", f"{'_'.join(w)}_{y}_{m:02d}", f"{'/'.join(w)}/{y}/{m:02d}/{camel}",
        )
        out.append(styles[k % len(styles)])
    return out


def _first_pass(docs: DataFrame) -> DataFrame:
    """One pass over the texts, landed: a row per document (base spans, tokens that the models must judge)
    and a row per task with its counts of character pairs, label * _N * _N + pair."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros(2 * _N * _N, np.int64)
        for b in batches:
            base, cands = [], []
            for x in b.column(1):
                text = x.as_py() or ""
                data = text.encode("utf-8", "surrogatepass")
                spans = base_spans(text)
                own = []
                if b"1" * LEAST_TOKEN in data.translate(_IS_TOKEN):
                    own = [f"{m.start()}:{m.end()}:{m.group()}" for m in _outside(TOKEN.finditer(text), spans)]
                if spans:  # what lies between the matches is ordinary
                    sums[_N * _N :] += _pairs(" ".join(t for s, _, e in spans for t in WORD.findall(text, s, e) if len(t) >= LEAST_TOKEN).encode())
                if spans or own:  # tokens still to be judged train neither model
                    judged = [(int(a), 3, int(e)) for a, e, _ in (x.split(":", 2) for x in own)]
                    data = masked(text, sorted(spans + judged), " ").encode("utf-8", "surrogatepass")
                sums[: _N * _N] += _pairs(data)
                base.append(told(spans))
                cands.append(own)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([True] * b.num_rows), pa.array(base), pa.array(cands, pa.list_(pa.string())), pa.nulls(b.num_rows, pa.list_(pa.int64()))], names=names)
        yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([False]), pa.array([""]), pa.array([[]], pa.list_(pa.string())), pa.array([sums.tolist()], pa.list_(pa.int64()))], names=names)

    names = ["doc_id", "is_doc", "base", "cands", "counts"]
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return common.land(rows.mapInArrow(run, "doc_id long, is_doc boolean, base string, cands array<string>, counts array<long>"), "secrets")


class MarkovPair:
    """Two first-order character models, backed by their own character frequencies; ratio() is
    log P_random - log P_ordinary."""

    def __init__(self, counts: dict[int, int]):
        """counts: of label * _N * _N + pair; label 1: random."""
        m = np.zeros(2 * _N * _N)
        for at, n in counts.items():
            m[at] += n
        m[_N * _N :] += _pairs(" ".join(random_samples()).encode())
        m[: _N * _N] += _pairs(" ".join(ordinary_samples()).encode())
        m = m.reshape(2, _N, _N)
        alone = m.sum(axis=1, keepdims=True) + 0.5
        alone /= alone.sum(axis=2, keepdims=True)
        p = np.log((m + BACKING * alone) / (m.sum(axis=2, keepdims=True) + BACKING))
        self.table = (p[1] - p[0]).ravel().tolist()
        self.least = self.best_threshold(SEED + 1)

    def best_threshold(self, seed: int) -> float:
        """Of RATIOS the one with the fewest misses and weighted false alarms on held-out samples; the middle of equals."""
        hot, cold = (np.array([self.ratio(t) for t in made(DRAWS, seed) if len(t) >= LEAST_TOKEN]) for made in (random_samples, ordinary_samples))
        cost = np.array([(hot < r).mean() + ALARM * (cold >= r).mean() for r in RATIOS])
        best = np.flatnonzero(cost <= cost.min() + 1e-12)
        return RATIOS[int(best[len(best) // 2])]

    def ratio(self, token: str) -> float:
        """Mean log-likelihood ratio per character."""
        last, total = 0, 0.0
        for c in token:
            k = _AT.get(c, 0)
            total += self.table[last * _N + k]
            last = k
        return total / max(1, len(token))

    def is_random(self, token: str) -> bool:
        return len(token) >= LEAST_TOKEN and self.ratio(token) >= self.least


def mixed(token: str) -> bool:
    """At least two digits and two letters; says what a token is like, no condition of being told."""
    digits = sum(map(token.count, "0123456789"))
    return digits >= 2 and sum(map(str.isalpha, token)) >= 2


def _train(first: DataFrame) -> MarkovPair:
    """At most 2 x 68 x 68 counts come to the driver, whatever the input."""
    sums = first.filter("not is_doc").select(F.posexplode("counts").alias("at", "n")).filter("n > 0").groupBy("at").agg(F.sum("n").alias("n"))
    return MarkovPair({r["at"]: r["n"] for r in sums.collect()})


def train(docs: DataFrame) -> MarkovPair:
    return _train(_first_pass(docs))


def all_spans(text: str, model: MarkovPair) -> list[Span]:
    spans = base_spans(text)
    more = [(m.start(), 3, m.end()) for m in _outside(TOKEN.finditer(text), spans) if model.is_random(m.group())]
    return sorted(spans + more)


def told(spans: list[Span]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def _spans(base: str, cands: list[str], model: MarkovPair) -> list[Span]:
    """What all_spans gives, from a row of the first pass."""
    spans = [(int(s), KINDS.index(k), int(e)) for k, s, e in (x.split(":") for x in base.split(",") if x)]
    for x in cands:
        s, e, token = x.split(":", 2)
        if model.is_random(token):
            spans.append((int(s), 3, int(e)))
    return sorted(spans)


def scan(docs: DataFrame) -> DataFrame:
    """Per row: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_markov.

    Null and empty texts have no spans and the digest of the empty string.  Rows are scanned one by one,
    so repeated ids, ties and other columns change nothing; doc_id may be null.
    """
    first = _first_pass(docs)
    model = _train(first)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for base, cands in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                spans = _spans(base, cands, model)
                n = Counter(k for _, k, _ in spans)
                rows.append((n[0], n[1], n[2], hashlib.sha256(base.encode()).hexdigest(), told(spans), n[3]))
            cols = [pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()))]
            yield pa.RecordBatch.from_arrays([b.column(0), *cols], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_markov"])

    out = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_markov long"
    return first.filter("is_doc").select("doc_id", "base", "cands").mapInArrow(run, out)


def masked(text: str, spans: list[Span], mark: str = "[secret]") -> str:
    out, at = [], 0
    for s, _, e in spans:
        if e <= at:
            continue
        if s >= at:
            out += [text[at:s], mark]
        at = e
    return "".join(out) + text[at:]


def mask_secrets(docs: DataFrame) -> DataFrame:
    """docs with every span replaced by a mark and n_chars set anew; nulls stay null."""
    model = train(docs)

    @F.pandas_udf("string")
    def mask(texts):
        return texts.map(lambda t: masked(t, all_spans(t, model)) if isinstance(t, str) else t)

    out = docs.withColumn("text", mask(F.col("text").cast("string")))
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out


def op2_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(common.read(spark, sf_dir, "documents"))


