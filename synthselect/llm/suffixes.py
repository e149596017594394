"""Suffix-array dedup: bytes of passages that occurred earlier, found over all documents.

A sparse enhanced suffix array: every 100-byte window is told by the smallest 32-byte hash within it (its
anchor), so equal windows have equal anchors at equal places, and only suffixes that start at anchors are
sorted.  Anchors are dealt by hash; their suffixes are sorted, the common-prefix intervals scanned with a
stack, and inside an interval the text to the left is treated the same way: an interval of left texts
that goes no further left or right is a maximal repeat, and it is told with all its occurrences.  All of
them but the earliest are removed.

Three things keep it small.  An anchor with the same text around it as an earlier one needs no bytes: all
its windows are repeats.  Bytes are fetched only for anchors whose surroundings differ, one of each kind; each task
first sifts its own anchors, so that a common passage leaves it once.  An anchor of very many kinds is split by the
bytes next to it: a window reaches so many bytes to its left, and those of one slice of reaches share a core, whose
digest takes the anchor's place; a slice still of very many kinds is told window by window, which aggregates.

repeat_groups() tells the maximal repeats themselves, each with all its occurrences.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .licenses import _sliding

LENGTH = 100
GRAM = 32
#: Long texts are anchored in parts that overlap by LENGTH - 1 bytes.
PART = 1 << 20
#: Kinds of one anchor that one interval scan takes.
MOST_KINDS = 2000
#: Anchors of a task that are sifted at a time, and kinds of one anchor among them that call for a closer look.
SIFTED, MANY = 400_000, 64
#: Parts into which the windows of an anchor of very many kinds are cut, by their reach to the left.
SLICES = 8

_SHIFT = np.uint64(20)
_LOW = np.uint64((1 << 20) - 1)
_TABLE = np.random.default_rng(97).integers(0, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_FACTORS = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def gram_hashes(data: np.ndarray) -> np.ndarray:
    """64-bit hash of each 32-byte gram, by doubling."""
    h = _TABLE[data]
    size = 1
    for f in _FACTORS:
        h = h[:-size] * f + h[size:]
        h ^= h >> np.uint64(29)
        size *= 2
    h = h * _FACTORS[0]
    return h ^ (h >> np.uint64(32))


def anchors(raw: bytes, length: int = LENGTH) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(hash, place, bytes to the left, bytes to the right) of the anchors of all windows of raw.

    The windows of an anchor follow one another; they cover raw[place - left : place + right].
    """
    hs, at, left, right = [], [], [], []
    data = np.frombuffer(raw, np.uint8)
    for lo in range(0, max(1, len(raw) - length + 1), PART - length + 1):
        part = data[lo : lo + PART]
        n = len(part) - length + 1
        if n <= 0:
            break
        h = gram_hashes(part)
        order = (h >> _SHIFT << _SHIFT) | np.arange(len(h), dtype=np.uint64)  # equal hashes: the leftmost
        own = (_sliding(order, length - GRAM + 1) & _LOW).astype(np.int64)
        first = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
        last = np.append(first[1:], n) - 1
        place = own[first]
        hs.append(h[place].view(np.int64))
        at.append(place + lo)
        left.append(place - first)
        right.append(last + length - place)
    if not hs:
        return (np.empty(0, np.int64),) * 4
    return tuple(map(np.concatenate, (hs, at, left, right)))  # type: ignore[return-value]


def _batches(docs: DataFrame, length: int, told) -> Iterator:
    """A function for mapInArrow: told(h, c, doc, tie, at) of SIFTED anchors or so of a task at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh64_intdigest
        out: list[list[np.ndarray]] = [[] for _ in range(5)]
        held = 0
        for b in batches:
            for d, t, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                raw = (text.as_py() or "").encode("utf-8", "surrogatepass")
                if len(raw) < length:
                    continue
                h, at, left, right = anchors(raw, length)
                c = np.fromiter((digest(raw[a - x : a + y], x) for a, x, y in zip(at.tolist(), left.tolist(), right.tolist())), np.uint64, len(at)).view(np.int64)
                for col, v in zip(out, (h, c, np.full(len(h), d), np.full(len(h), t), at << 16 | left << 8 | right)):
                    col.append(v)
                held += len(h)
                if held > SIFTED:
                    yield from told(*map(np.concatenate, out))
                    out, held = [[] for _ in range(5)], 0
        if held:
            yield from told(*map(np.concatenate, out))

    return run


def _very_many(docs: DataFrame, length: int) -> np.ndarray:
    """Anchors of more than MOST_KINDS kinds, sorted: those of which some task has MANY among the SIFTED.

    A first pass that only counts.  It decides where rows are dealt, never what is found, so the largest
    common.MOST_SENT are enough.
    """

    def told(h, c, doc, tie, at) -> Iterator[pa.RecordBatch]:
        order = np.lexsort((c, h))
        h, c = h[order], c[order]
        new_h = np.append(True, h[1:] != h[:-1])
        kind = new_h | np.append(True, c[1:] != c[:-1])
        first = np.flatnonzero(new_h)
        n = np.add.reduceat(kind.astype(np.int64), first)
        ok = n >= MANY
        if ok.any():
            yield pa.RecordBatch.from_arrays([pa.array(h[first[ok]]), pa.array(n[ok])], names=["h", "n"])

    n = docs.select("doc", "tie", "text").mapInArrow(_batches(docs, length, told), "h long, n long").groupBy("h").agg(F.sum("n").alias("n"))
    rows = n.filter(F.col("n") > MOST_KINDS).orderBy(F.desc("n"), "h").limit(common.MOST_SENT).collect()  # <= MOST_SENT numbers
    return np.array(sorted(r["h"] for r in rows), np.int64)


_ROWS = "h long, c long, doc long, tie long, at long, stop long, sub long"


def _anchor_rows(docs: DataFrame, length: int, many: np.ndarray) -> DataFrame:
    """Rows of _ROWS: the earliest anchor of each kind among those sifted together, stop -1, and the spans (doc, tie,
    at: start, stop) of the others, joined.

    c: a digest of the text around the anchor; at packs place, left and right; sub: c where h is of very many kinds.
    """

    def told(h, c, doc, tie, at) -> Iterator[pa.RecordBatch]:
        order = np.lexsort((at, tie, doc, c, h))
        first = np.append(True, (h[order][1:] != h[order][:-1]) | (c[order][1:] != c[order][:-1]))
        a, z = order[first], order[~first]
        sub = np.where(np.isin(h[a], many), c[a], 0)
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (h[a], c[a], doc[a], tie[a], at[a], np.full(len(a), -1), sub)], names=names)
        if len(z):
            d, t, start = doc[z], tie[z], (at[z] >> 16) - (at[z] >> 8 & 255)
            stop = (at[z] >> 16) + (at[z] & 255)
            by = np.lexsort((stop, start, t, d))
            d, t, start, stop = d[by], t[by], start[by], stop[by]
            # within a text later starts have later stops
            new = np.append(True, (d[1:] != d[:-1]) | (t[1:] != t[:-1]) | (start[1:] > stop[:-1]))
            at_ = np.flatnonzero(new)
            end = stop[np.append(at_[1:], len(stop)) - 1]
            k = np.arange(len(at_))
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (d[at_] * 31 + k, k * 0, d[at_], t[at_], start[at_], end, k * 0)], names=names)

    names = [x.split()[0] for x in _ROWS.split(", ")]
    return docs.select("doc", "tie", "text").mapInArrow(_batches(docs, length, told), _ROWS)


def _first_sift(rows: DataFrame, many: np.ndarray) -> DataFrame:
    """Landed rows (h, doc, tie, at, stop): spans of anchors whose surroundings occurred earlier (at: start), and with
    stop -1 the earliest of each kind, where an anchor has several.  Streams over sorted rows, a state of one row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: list[int] | None = None  # previous row
        head: list[int] | None = None  # first row of the current h, not told yet
        kinds = 0
        for b in batches:
            span = np.asarray(b.column(5)) >= 0
            if span.any():
                yield pa.RecordBatch.from_arrays([b.column(k).filter(pa.array(span)) for k in (0, 2, 3, 4, 5)], names=names)
                b = b.filter(pa.array(~span))
            if not b.num_rows:
                continue
            h, c, doc, tie, at = (x.to_numpy() for x in b.columns[:5])
            prev = [np.concatenate([[last[k] if last else 0], x[:-1]]) for k, x in enumerate((h, c, doc, tie, at))]
            new_h, same = h != prev[0], (doc == prev[2]) & (tie == prev[3]) & (at == prev[4])
            if last is None:
                new_h[0] = True
            new_c = new_h | (c != prev[1])
            seen = ~new_c & ~same
            # number of the kind within its h
            run_of = np.cumsum(new_c)
            heads = np.flatnonzero(new_h)
            base = np.zeros(len(h), np.int64)
            group = np.cumsum(new_h) - 1
            if len(heads):
                base[group >= 0] = run_of[heads][group[group >= 0]]
            kind = np.where(group >= 0, run_of - base, run_of + kinds)
            second = new_c & (kind == 1)
            told = new_c & ((kind >= 1) | np.isin(h, many))
            extra: list[list[int]] = []
            for i in np.flatnonzero(second):
                if group[i] < 0:
                    if head[0] not in many_:  # type: ignore[index]
                        extra.append(head)  # type: ignore[arg-type]
                else:
                    told[heads[group[i]]] = True
            pick = np.flatnonzero(seen | told)
            place, flag = at[pick] >> 16, seen[pick]
            start, stop = np.where(flag, place - (at[pick] >> 8 & 255), at[pick]), np.where(flag, place + (at[pick] & 255), -1)
            cols = [h[pick], doc[pick], tie[pick], start, stop]
            if extra:
                cols = [np.append(x, e) for x, e in zip(cols, ([e[0] for e in extra], [e[2] for e in extra], [e[3] for e in extra], [e[4] for e in extra], [-1] * len(extra)))]
            if len(cols[0]):
                yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in cols], names=names)
            last = [int(x[-1]) for x in (h, c, doc, tie, at)]
            kinds = int(kind[-1])
            if len(heads):
                head = [int(x[heads[-1]]) for x in (h, c, doc, tie, at)]

    names = ["h", "doc", "tie", "at", "stop"]
    many_ = set(many.tolist())
    rows = rows.repartition("h", "sub").sortWithinPartitions("h", "c", "doc", "tie", "at")
    return common.land(rows.mapInArrow(run, "h long, doc long, tie long, at long, stop long"), "sifted")


def _shared(a: int, b: int, width: int) -> int:
    """Equal leading bytes of two numbers of `width` bytes."""
    x = a ^ b
    return width if not x else width - (x.bit_length() + 7) // 8


def intervals(lcp: list[int]) -> Iterator[tuple[int, int, int]]:
    """(depth, first, last) of the common-prefix intervals of a sorted list; lcp[i] is shared by i - 1 and i."""
    stack = [(0, 0)]
    n = len(lcp)
    for i in range(1, n + 1):
        depth = lcp[i] if i < n else 0
        first = i - 1
        while stack[-1][0] > depth:
            d, first = stack.pop()
            yield d, first, i - 1
        if stack[-1][0] < depth:
            stack.append((depth, first))


_LEFT, _RIGHT = LENGTH, 2 * LENGTH


def maximal_repeats(left: list[bytes], right: list[bytes], length: int = LENGTH) -> Iterator[tuple[int, int, list[int]]]:
    """(bytes to the left, to the right, members): repeats of at least `length` bytes through a common point.

    left: texts before it, nearest byte first; right: texts after it.  Each is extended as far as all its
    members agree on both sides.
    """
    m = len(left)
    rw = max(map(len, right)) if m else 0
    lw = max(map(len, left)) if m else 0
    rnum = [int.from_bytes(x.ljust(rw, b"\0"), "big") for x in right]
    lnum = [int.from_bytes(x.ljust(lw, b"\0"), "big") for x in left]
    rlen, llen = list(map(len, right)), list(map(len, left))
    order = sorted(range(m), key=lambda i: (rnum[i], rlen[i]))
    lcp = [0] + [min(_shared(rnum[a], rnum[b], rw), rlen[a], rlen[b]) for a, b in zip(order, order[1:])]
    for depth, first, last in intervals(lcp):
        if depth + lw < length:
            continue
        # of this interval's members, in the order of their left texts
        own = sorted(range(first, last + 1), key=lambda k: (lnum[order[k]], llen[order[k]]))
        lcs = [0] + [min(_shared(lnum[order[a]], lnum[order[b]], lw), llen[order[a]], llen[order[b]]) for a, b in zip(own, own[1:])]
        need = length - depth
        spans = list(intervals(lcs)) if need > 0 else [*intervals(lcs), (0, 0, len(own) - 1)]
        for back, lo, hi in spans:
            if back + depth < length:
                continue
            at = own[lo : hi + 1]
            a, z = min(at), max(at)
            if min(lcp[a + 1 : z + 1]) > depth:
                continue  # goes further right: a deeper interval tells it
            yield back, depth, [order[k] for k in at]


def _repeats(rows: DataFrame, length: int) -> DataFrame:
    """Spans (doc, tie, start, stop) of all but the earliest occurrences; rows: h (a group), doc, tie, at, around."""

    def pairs(first: np.ndarray, left, right, around) -> Iterator[tuple[np.ndarray, ...]]:
        """The groups of two at once: rows first and first + 1."""
        for k in range(0, len(first), 20_000):
            a = first[k : k + 20_000]
            b = a + 1
            ls, rs = np.zeros(len(a), np.int64), np.zeros(len(a), np.int64)
            for side, out, width in ((0, ls, int(left.max()) + 1), (1, rs, int(right.max()) + 1)):
                mats = []
                for r in (a, b):
                    cut = [around[i][: left[i]][::-1] if side == 0 else around[i][left[i] :] for i in r]
                    mats.append(np.frombuffer(b"".join(x.ljust(width, b"\0") for x in cut), np.uint8).reshape(len(a), width))
                n = (left if side == 0 else right)
                differ = mats[0] != mats[1]
                differ[:, -1] = True
                out[:] = np.minimum(differ.argmax(axis=1), np.minimum(n[a], n[b]))
            ok = ls + rs >= length
            yield b[ok], ls[ok], rs[ok]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf, starts in common.whole_runs(batches, ["h"], 20_000):
            doc, tie, at = (pdf[k].to_numpy() for k in ("doc", "tie", "at"))
            place, left, right = at >> 16, at >> 8 & 255, at & 255
            around = pdf["around"].tolist()
            sizes = np.diff(np.append(starts, len(pdf)))
            # every span holds its anchor, so an occurrence's spans join: the farthest on either side
            back, ahead = np.full(len(pdf), -1), np.full(len(pdf), -1)
            for rows_, ls, rs in pairs(starts[sizes == 2], left, right, around):
                back[rows_], ahead[rows_] = ls, rs
            for s, m in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist()):
                lefts = [around[i][: left[i]][::-1] for i in range(s, s + m)]
                rights = [around[i][left[i] :] for i in range(s, s + m)]
                for x, y, members in maximal_repeats(lefts, rights, length):
                    members = np.array(members)
                    later = s + members[members != members.min()]  # rows are in the order of documents and places
                    back[later] = np.maximum(back[later], x)
                    ahead[later] = np.maximum(ahead[later], y)
            w = np.flatnonzero(back >= 0)
            yield pd.DataFrame({"doc": doc[w], "tie": tie[w], "start": place[w] - back[w], "stop": place[w] + ahead[w]})

    rows = rows.repartition("h").sortWithinPartitions("h", "doc", "tie", "at")
    return rows.mapInPandas(run, "doc long, tie long, start long, stop long")


def _reaches(length: int) -> list[tuple[int, int]]:
    """The slices [lo, hi] of bytes that a window may reach to the left of its anchor."""
    cuts = [(length - GRAM + 1) * k // SLICES for k in range(SLICES + 1)]
    return [(lo, hi - 1) for lo, hi in zip(cuts, cuts[1:]) if hi > lo]


def _sliced(rows: DataFrame, length: int) -> DataFrame:
    """(h, doc, tie, at, around, slice) for every slice that a row has windows in; h: a digest of the slice's core."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k0 in range(0, b.num_rows, 2000):
                out = []
                for h, d, t, at, around in zip(*(c.to_pylist() for c in b.slice(k0, 2000).columns)):
                    left, right = at >> 8 & 255, at & 255
                    for k, (lo, hi) in enumerate(_reaches(length)):
                        # its windows reach from `lo` bytes left, as far as there are, to `length` - `hi` right
                        lo_, hi_ = max(lo, length - right), min(hi, left)
                        if lo_ <= hi_:
                            core = around[left - lo : left + length - hi]
                            out.append((xxhash.xxh64_intdigest(core, (h ^ k) & (2**64 - 1)) - 2**63, d, t, at, around, k))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(zip(*out), types)], names=names)

    names, types = ["h", "doc", "tie", "at", "around", "slice"], (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int32())
    return rows.select("h", "doc", "tie", "at", "around").mapInArrow(run, "h long, doc long, tie long, at long, around binary, slice int")


def _windows(rows: DataFrame, length: int) -> DataFrame:
    """The same spans for slices of very many kinds: every window of the slice by its 128-bit digest."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k0 in range(0, b.num_rows, 2000):
                out = []
                for d, t, at, around, k in zip(*(c.to_pylist() for c in b.slice(k0, 2000).columns)):
                    place, left, right = at >> 16, at >> 8 & 255, at & 255
                    lo, hi = _reaches(length)[k]
                    for a in range(max(lo, length - right), min(hi, left) + 1):
                        out.append((xxhash.xxh3_128_digest(around[left - a : left - a + length]), d, t, place - a))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(zip(*out), (pa.binary(), pa.int64(), pa.int64(), pa.int64()))], names=["w", "doc", "tie", "start"])

    wins = common.land(rows.select("doc", "tie", "at", "around", "slice").mapInArrow(run, "w binary, doc long, tie long, start long"), "windows")
    first = wins.groupBy("w").agg(F.min(F.struct("doc", "tie", "start")).alias("low"), F.count(F.lit(1)).alias("_n"))
    later = common.join_spread(wins, first, "w", "_n", wins.count()).filter("struct(doc, tie, start) <> low")
    return later.select("doc", "tie", "start", (F.col("start") + length).alias("stop"))


def _scanned(asked: DataFrame, per: DataFrame, length: int, sliced: bool = False) -> DataFrame:
    """Spans of the rows (h, doc, tie, at, around); groups of more than MOST_KINDS rows are cut finer."""
    hot = common.land(per.filter(F.col("n") > MOST_KINDS).select("h"), "hot")
    if not hot.limit(1).count():
        return _repeats(asked, length)
    asked, hot = common.land(asked, "around"), common.sent(hot)
    cold, rest = _repeats(asked.join(hot, "h", "left_anti"), length), asked.join(hot, "h", "left_semi")
    if sliced:
        return cold.union(_windows(rest, length))
    finer = common.land(_sliced(rest, length), "slices")
    return cold.union(_scanned(finer, finer.groupBy("h").agg(F.count(F.lit(1)).alias("n")), length, True))


def _keyed(docs: DataFrame) -> DataFrame:
    """doc: the doc_id, null before all; tie: tells rows of one id apart, in the order of a 128-bit digest of their
    texts, 0 where no id is repeated."""
    d = docs.withColumn("doc", F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))))
    many = d.groupBy("doc").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("doc")
    if not many.limit(1).count():
        return d.withColumn("tie", F.lit(0).cast("long"))
    d = d.withColumn("_digest", F.md5(F.coalesce("text", F.lit("")).cast("binary")))
    kinds = d.select("doc", "_digest").distinct().repartitionByRange("doc", "_digest").sortWithinPartitions("doc", "_digest")
    kinds = common.land(kinds.withColumn("tie", F.monotonically_increasing_id()), "ties")
    return d.join(kinds, ["doc", "_digest"]).drop("_digest")


def repeat_groups(docs: DataFrame, length: int = LENGTH, reach: int = 1000) -> DataFrame:
    """(repeat, n_bytes, n_occurrences, doc_id, start): every maximal repeat of at least `length` bytes with all its
    occurrences, a row each; start: in bytes; repeat: the hex digest of its bytes.

    Maximal: no byte more on either side is the same at all occurrences; the ends of a text differ from everything.
    Repeats are seen as far as `reach` bytes around an anchor, and told cut there.  Null and short texts have none; rows
    of one doc_id are told apart as in dedup_bytes, equal ones as one document.  Occurrences with the same bytes
    around them are one kind; a task holds the kinds of an anchor, not its occurrences.
    """

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for d, t, text in zip(*(c.to_pylist() for c in b.columns)):
                raw = (text or "").encode("utf-8", "surrogatepass")
                if len(raw) >= length:
                    h, at, left, right = (x.tolist() for x in anchors(raw, length))
                    around = [raw[max(0, p - reach) : p + reach] for p in at]
                    back = [min(p, reach) for p in at]
                    kind = [xxhash.xxh3_128_digest(x, k) for x, k in zip(around, back)]
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in (h, kind, [d] * len(h), [t] * len(h), at, back, left, right, around)], names=["h", "kind", "doc", "tie", "at", "back", "left", "right", "around"])

    def tell(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf, starts in common.whole_runs(batches, ["h"], 2_000):
            out = []
            for s, e in zip(starts.tolist(), [*starts.tolist()[1:], len(pdf)]):
                rows = pdf.iloc[s:e]
                own = np.repeat(np.arange(e - s), np.minimum(rows["n"], 2))  # copies of a kind repeat it whole
                around, back = rows["around"].tolist(), rows["back"].tolist()
                found: dict[tuple, int] = {}
                for x, y, members in maximal_repeats([around[k][: back[k]][::-1] for k in own], [around[k][back[k] :] for k in own], length):
                    key = (y, frozenset(members))
                    found[key] = max(x, found.get(key, 0))
                for (y, members), x in found.items():
                    k = int(own[min(members)])
                    # the anchor is that of a window within the repeat, so all its occurrences are here
                    if max(length - y, length - rows["right"].iloc[k]) <= min(x, rows["left"].iloc[k]):
                        name = xxhash.xxh3_128_hexdigest(around[k][back[k] - x : back[k] + y])
                        out += [(rows["h"].iloc[0], rows["kind"].iloc[int(i)], name, x + y, x) for i in {own[m] for m in members}]
            yield pd.DataFrame(out, columns=["h", "kind", "repeat", "n_bytes", "x"])

    keyed = _keyed(docs.select("doc_id", F.col("text").cast("string").alias("text")))
    names = "h long, kind binary, doc long, tie long, at long, back long, left long, right long, around binary"
    rows = common.land(keyed.select("doc", "tie", "text").distinct().mapInArrow(cut, names), "contexts")
    one = F.struct("back", "left", "right", "around")
    kinds = rows.groupBy("h", "kind").agg(F.count(F.lit(1)).alias("n"), F.min(one).alias("c"))
    twice = rows.groupBy("h").agg(F.count(F.lit(1)).alias("m")).filter("m > 1").select("h")
    kinds = kinds.join(twice, "h", "left_semi").select("h", "kind", "n", "c.*").repartition("h").sortWithinPartitions("h", "kind")
    found = common.land(kinds.mapInPandas(tell, "h long, kind binary, repeat string, n_bytes long, x long"), "groups")
    met = rows.select("h", "kind", "doc", "tie", "at").join(found, ["h", "kind"])
    met = met.select("repeat", "n_bytes", "doc", "tie", (F.col("at") - F.col("x")).alias("start")).distinct()
    n = met.groupBy("repeat").agg(F.count(F.lit(1)).alias("n_occurrences"))
    return met.join(n, "repeat").select("repeat", "n_bytes", "n_occurrences", F.expr(f"nullif(doc, {-(1 << 63)})").alias("doc_id"), "start")


def _packed(docs: DataFrame) -> DataFrame:
    """(doc, tie, z): texts compressed for the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3).compress
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([pack((t or "").encode("utf-8", "surrogatepass")) for t in b.column(2).to_pylist()], pa.binary())], names=["doc", "tie", "z"])

    return docs.select("doc", "tie", "text").mapInArrow(run, "doc long, tie long, z binary")


def repeated_spans(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """Landed (doc, tie, start, stop): bytes covered by a `length`-byte string that also starts earlier; may overlap."""
    many = _very_many(docs, length)
    sifted = _first_sift(_anchor_rows(docs, length, many), many)
    seen = sifted.filter("stop >= 0").select("doc", "tie", F.col("at").alias("start"), "stop")
    ask = sifted.filter("stop < 0").groupBy("doc", "tie").agg(F.collect_list(F.struct("h", "at")).alias("ask"))

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 64):
                rows = []
                for d, t, z, ask in zip(*(c.to_pylist() for c in b.slice(lo, 64).columns)):
                    raw = zstandard.ZstdDecompressor().decompress(z)
                    for x in ask:
                        at = x["at"]
                        rows.append((x["h"], d, t, at, raw[(at >> 16) - (at >> 8 & 255) : (at >> 16) + (at & 255)]))
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()))], names=["h", "doc", "tie", "at", "around"])

    kinds = "h long, doc long, tie long, at long, around binary"
    asked = _packed(docs).join(ask, ["doc", "tie"]).select("doc", "tie", "z", "ask").mapInArrow(fetch, kinds)
    per = sifted.filter("stop < 0").groupBy("h").agg(F.count(F.lit(1)).alias("n"))
    return _scanned(asked, per, length).union(seen)


def _merged(spans: list[dict], n: int) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for s, e in sorted((x["start"], x["stop"]) for x in (() if spans is None else spans)):
        if out and s <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([s, e])
    return [(s, e) for s, e in out]


def _with_spans(docs: DataFrame, spans: DataFrame) -> DataFrame:
    per = spans.groupBy("doc", "tie").agg(F.collect_list(F.struct("start", "stop")).alias("spans"))
    return docs.join(per, ["doc", "tie"], "left")


def dedup_bytes(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256.

    Null texts count as empty; texts shorter than `length` bytes lose nothing.  A null doc_id comes before
    all others.  Rows that share a doc_id are told apart and ordered by a digest of their text; equal rows
    are one document and both get its result.  Other columns aren't looked at.
    """
    import hashlib

    keyed = _keyed(docs.select("doc_id", F.col("text").cast("string").alias("text")))
    spans = repeated_spans(keyed, length)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for z, own in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                raw = zstandard.ZstdDecompressor().decompress(z)
                cut = _merged(own, len(raw))
                kept, at = [], 0
                for s, e in cut:
                    kept.append(raw[at:s])
                    at = e
                kept.append(raw[at:])
                out.append((len(raw), sum(e - s for s, e in cut), len(cut), hashlib.sha256(b"".join(kept)).hexdigest()))
            cols = list(zip(*out)) or [(), (), (), ()]
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, k) for c, k in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.string())))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    rows = _with_spans(_packed(keyed), spans).select(F.expr(f"nullif(doc, {-(1 << 63)})").alias("doc_id"), "z", "spans")
    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def drop_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """docs with those bytes cut out of text (a character cut in two goes) and n_chars set anew; nulls stay."""
    keyed = _keyed(docs.select("doc_id", F.col("text").cast("string").alias("text"), F.struct(*docs.columns).alias("row")))
    spans = repeated_spans(keyed.select("doc", "tie", "text"), length)

    @F.pandas_udf("string")
    def cut(texts: pd.Series, spans: pd.Series) -> pd.Series:
        out = []
        for t, own in zip(texts, spans):
            if not isinstance(t, str) or own is None or not len(own):
                out.append(t)
                continue
            raw = t.encode("utf-8", "surrogatepass")
            kept, at = [], 0
            for s, e in _merged(own, len(raw)):
                kept.append(raw[at:s].decode("utf-8", "ignore"))
                at = e
            out.append("".join(kept) + raw[at:].decode("utf-8", "ignore"))
        return pd.Series(out, dtype=object)

    rows = _with_spans(keyed, spans).select("row", cut("text", "spans").alias("text"))
    new = {"text": F.col("text"), "n_chars": F.length("text").cast("long")}
    return rows.select(*[new.get(c, F.col("row")[c]).alias(c) for c in docs.columns])


def op9_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_bytes(common.read(spark, sf_dir, "documents"))
