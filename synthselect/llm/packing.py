"""Best-fit packing of token sequences, bulk-synchronous.

Documents' pieces are packed class by class, the longest first; a class's lengths lie within a factor of two.
A round range-sorts the class's unplaced pieces and the gaps that may hold one, longest first, and sweeps each
range: a piece goes to its successor, the smallest gap left that holds it, and the gap's rest is put back in its
place.  Pieces without a successor in their own range turn to the ranges of larger gaps: what is left there is
counted range by range, and pieces that want the same gaps are dealt to them by rank.  Then the gaps are updated
and the round is repeated; what no gap holds gets new sequences before the next.  Every round meets the next
through landed files, and of each range two counts reach the driver.
"""

from __future__ import annotations

import heapq
import re
import string
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common
from .tokencount import tokenizer_path

CAPACITY = 2048
END_ID = 0
#: Pieces and gaps of one range, about.
RANGE_ROWS = 40_000
#: Pieces of at most so many ids are one class, the last.
SHORT = 64
MOST_CACHED = 400_000
LONGEST_CACHED = 48

#: Characters whose case, composition and classes are the same in every Unicode release, without blanks
#: that libraries see differently; a text of other characters goes to the tokenizer library whole.
PLAIN = re.compile("[\t-\r -~¡-įı-ɏ]*")


class WordIds:
    """ids of texts by a lower-casing word tokenizer that drops white space.

    Nothing reaches across white space, so ids are kept per blank-separated chunk.  The library makes them,
    many at a time: a word of letters alone ends with its first id that closes a word.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(path)
        self.specials = [t.content for t in self.lib.get_added_tokens_decoder().values()]
        self.cache: dict[str, bytes] = {}
        self.words: dict[str, bytes] = {}
        self.closes = np.zeros(self.lib.get_vocab_size(with_added_tokens=True) + 1, bool)
        for token, k in self.lib.get_vocab(with_added_tokens=False).items():
            self.closes[k] = token.endswith("</w>")

    def _ask_words(self, words: list[str]) -> None:
        """Ids of words that are one run of letters or of marks each."""
        for part, ids in zip(groups := [words[k : k + 500] for k in range(0, len(words), 500)], self._ask([" ".join(g) for g in groups])):
            ends = np.flatnonzero(self.closes[np.frombuffer(ids, "<u4")]) + 1
            if len(ends) != len(part):
                raise ValueError("a word did not end where expected")
            cut = [0, *(4 * ends).tolist()]
            self.words.update(zip(part, (ids[i:j] for i, j in zip(cut, cut[1:]))))

    def _learn(self, chunks: list[str]) -> None:
        parts, odd, need = [], [], set()
        for c in chunks:
            low = c.lower()
            core = low.rstrip(string.punctuation)
            if core.isalpha():
                parts.append((c, core, tail := low[len(core) :]))
                need.add(core)
                if tail:
                    need.add(tail)
            else:
                odd.append(c)
        self._ask_words(list(need.difference(self.words)))
        get = self.words.__getitem__
        self.cache.update((c, get(core) + get(tail) if tail else get(core)) for c, core, tail in parts)
        self.cache.update(zip(odd, self._ask(odd)))
        if len(self.words) > MOST_CACHED:
            self.words.clear()

    def _ask(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.lib.encode_batch_fast(texts, add_special_tokens=False)]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        out: list[bytes | None] = [None] * len(texts)
        odd, chunks = [], {}
        for k, t in enumerate(texts):
            if PLAIN.fullmatch(t) and not any(s in t for s in self.specials):
                chunks[k] = t.split()
            else:
                odd.append(k)
        if odd:
            for k, ids in zip(odd, self._ask([texts[k] for k in odd])):
                out[k] = ids
        new = list(set().union(*chunks.values()).difference(self.cache)) if chunks else []
        self._learn(new)
        get = self.cache.__getitem__
        for k, c in chunks.items():
            out[k] = b"".join(map(get, c))
        if len(self.cache) > MOST_CACHED:
            self.cache.clear()
        else:
            for w in new:
                if len(w) > LONGEST_CACHED:
                    del self.cache[w]
        return out  # type: ignore[return-value]


_LOADED: dict[str, WordIds] = {}


def _unload() -> None:
    """Give back what a worker that is used again holds of the tokenizer."""
    import ctypes
    import gc

    if _LOADED:
        _LOADED.clear()
        gc.collect()
        try:
            ctypes.CDLL("libc.so.6").malloc_trim(0)
        except (OSError, AttributeError):
            pass  # another C library: memory is reused all the same


def cut_pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """Landed rows (doc_id, piece, start, length, ids_crc32, pid): documents as pieces of at most `capacity` ids;
    pid tells the pieces apart."""
    names = ["doc_id", "piece", "start", "length", "ids_crc32", "pid"]
    end = np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        file = path or tokenizer_path("word_bpe_49k.json")
        if file not in _LOADED:
            _LOADED[file] = WordIds(file)
        words = _LOADED[file]
        pid = TaskContext.get().partitionId() << 40
        for b in batches:
            for lo in range(0, b.num_rows, 128):
                ids, texts = (c.to_pylist() for c in b.slice(lo, 128).columns)
                rows = []
                for d, data in zip(ids, words.encode([t or "" for t in texts])):
                    data += end
                    for k in range(0, len(data), 4 * capacity):
                        cut = data[k : k + 4 * capacity]
                        rows.append((d, k // (4 * capacity), k // 4, len(cut) // 4, zlib.crc32(cut), pid))
                        pid += 1
                cols = list(zip(*rows))
                types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], names=names)

    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    return common.land(rows.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, pid long"), "pieces")


def classes(capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(lo, hi] of the lengths of each class, the longest first."""
    out, hi = [], capacity
    while hi > SHORT:
        out.append((hi // 2, hi))
        hi //= 2
    return [*out, (0, hi)]


GAP, PIECE = 0, 1


class Sweep:
    """Best fit within a range that comes longest first: take() a block of rows, then left()."""

    def __init__(self, least: int):
        self.least = least  # gaps of no more hold no piece of the class
        self.stack: list[tuple[int, int]] = []  # (size, sequence), the smallest on top
        self.rests: list[tuple[int, int]] = []  # (-size, sequence) of gaps to be put back further down
        self.small: list[tuple[int, int]] = []
        self.alone: list[tuple[int, int]] = []  # (piece, length) without a gap

    def _put_back(self, size: int) -> None:
        while self.rests and -self.rests[0][0] >= size:
            s, seq = heapq.heappop(self.rests)
            self.stack.append((-s, seq))

    def take(self, sizes: list[int], kinds: list[int], ids: list[int]) -> tuple[list[int], list[int], list[int]]:
        """(piece, sequence, size of the gap it went to) of the pieces placed."""
        pieces, sequences, gaps = [], [], []
        for size, kind, k in zip(sizes, kinds, ids):
            if self.rests:
                self._put_back(size)
            if kind == GAP:
                self.stack.append((size, k))
            elif not self.stack:
                self.alone.append((k, size))
            else:
                gap, seq = self.stack.pop()
                pieces.append(k)
                sequences.append(seq)
                gaps.append(gap)
                rest = gap - size
                if rest >= size:
                    self.stack.append((rest, seq))
                elif rest > self.least:
                    heapq.heappush(self.rests, (-rest, seq))
                elif rest:
                    self.small.append((rest, seq))
        return pieces, sequences, gaps

    def left(self) -> list[tuple[int, int]]:
        """(size, sequence) of the gaps that hold any piece of the ranges to come, the smallest first."""
        return self.stack[::-1]

    def below(self) -> list[tuple[int, int]]:
        """(size, sequence) of the other gaps."""
        return self.small + [(-s, seq) for s, seq in self.rests]


def deal(alone: list[int], slots: list[int]) -> tuple[np.ndarray, list[int]]:
    """Who takes what by rank: alone and slots, counted by range, the longest first.

    Rows (range, first rank, how many, range of the gaps, first slot), sorted; and the slots taken of each range.
    A range's pieces take the nearest range of larger gaps that has slots, its smallest gaps first.
    """
    rows, taken, open_ = [], [0] * len(slots), []
    for p, n in enumerate(alone):
        rank = 0
        while rank < n and open_:
            q = open_[-1]
            m = min(n - rank, slots[q] - taken[q])
            if m:
                rows.append((p, rank, m, q, taken[q]))
                taken[q] += m
                rank += m
            if taken[q] == slots[q]:
                open_.pop()
        if slots[p]:
            open_.append(p)
    return np.array(rows, np.int64).reshape(-1, 5), taken


_SWEPT = "kind int, id long, size long, seq long, gap long, rank long, slots long, part int"


def _sweep(pieces: DataFrame, gaps: DataFrame, lo: int, hi: int, n: int) -> DataFrame:
    """Landed rows of every range: pieces placed (seq, gap: the gap's size before), pieces alone (rank), gaps (rank: first slot)."""
    ranges = -(-n // RANGE_ROWS)
    rows = gaps.select(F.col("gap").alias("size"), F.lit(GAP).alias("kind"), F.col("seq").alias("id")).union(pieces.select(F.col("length").alias("size"), F.lit(PIECE).alias("kind"), F.col("pid").alias("id")))
    order = [F.desc("size"), "kind", "id"]
    names = [c.split()[0] for c in _SWEPT.split(", ")]
    types = [pa.int32(), *[pa.int64()] * 6, pa.int32()]

    def out(kind: int, part: int, size, ids, seq=0, gap=0, rank=0, slots=0) -> pa.RecordBatch:
        n = len(ids)
        cols = (kind, ids, size, seq, gap, rank, slots, part)
        return pa.RecordBatch.from_arrays([pa.array(np.broadcast_to(np.asarray(c, np.int64), n), pa.int64()).cast(t) for c, t in zip(cols, types)], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _unload()
        part, sweep = TaskContext.get().partitionId(), Sweep(lo)
        for b in batches:
            ids, seqs, sizes = sweep.take(*(c.to_pylist() for c in b.columns))
            if ids:
                yield out(PIECE, part, 0, ids, seqs, sizes)
        if sweep.alone:
            ids, lengths = zip(*sweep.alone)
            yield out(PIECE, part, lengths, ids, -1, 0, np.arange(len(ids)))
        for many, slot in ((sweep.left(), True), (sweep.below(), False)):
            if many:
                size, seq = (np.array(x, np.int64) for x in zip(*many))
                k = np.maximum(1, size // hi) if slot else np.zeros(len(size), np.int64)
                yield out(GAP, part, size, seq, rank=np.cumsum(k) - k, slots=k)

    rows = rows.repartitionByRange(ranges, *order).sortWithinPartitions(*order)
    return common.land(rows.mapInArrow(run, _SWEPT), "swept")


def _dealt(swept: DataFrame, rows: np.ndarray, taken: list[int], capacity: int) -> DataFrame:
    """Landed (pid, seq, offset, rest): pieces of one range placed in gaps of others; rest: what is left of the gap after the piece."""
    key = rows[:, 0] << 40 | rows[:, 1]
    taken_ = np.array(taken, np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            part, rank = (b.column(k).to_numpy().astype(np.int64) for k in (2, 3))
            at = np.searchsorted(key, part << 40 | rank, side="right") - 1
            row = rows[np.maximum(at, 0)]
            ok = (at >= 0) & (row[:, 0] == part) & (rank < row[:, 1] + row[:, 2])
            yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array(ok)), b.column(1).filter(pa.array(ok)), pa.array(row[ok, 3]), pa.array(row[ok, 4] + rank[ok] - row[ok, 1])], names=["pid", "length", "q", "slot"])

    def used(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            part, first, slots = (b.column(k).to_numpy().astype(np.int64) for k in (2, 3, 4))
            n = np.clip(taken_[part] - first, 0, slots)
            seq, gap = (np.repeat(b.column(k).to_numpy(), n) for k in (0, 1))
            slot = np.repeat(first, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (seq, gap, np.repeat(part, n), slot)], names=["seq", "gap", "q", "slot"])

    alone = swept.filter(f"kind = {PIECE} and seq = -1").select(F.col("id").alias("pid"), F.col("size").alias("length"), "part", "rank")
    gaps = swept.filter(f"kind = {GAP} and slots > 0").select(F.col("id").alias("seq"), F.col("size").alias("gap"), "part", "rank", "slots")
    met = alone.mapInArrow(run, "pid long, length long, q long, slot long").join(gaps.mapInArrow(used, "seq long, gap long, q long, slot long"), ["q", "slot"])
    w = Window.partitionBy("seq").orderBy("slot")  # at most capacity / SHORT slots a sequence
    met = met.withColumn("rest", F.col("gap") - F.sum("length").over(w))
    return common.land(met.select("pid", "seq", (capacity - F.col("rest") - F.col("length")).alias("offset"), "rest"), "dealt")


def place(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """(pid, seq, offset) of every piece (pid, length); seq: any numbers."""
    bounds = classes(capacity)
    lo = bounds[0][0]
    sums = pieces.groupBy(*[(F.col("length") > x).alias(f"over{k}") for k, (x, _) in enumerate(bounds)]).agg(F.count(F.lit(1)).alias("n")).collect()  # one row a class
    members = [sum(r["n"] for r in sums if r[f"over{k}"]) for k in range(len(bounds))]
    members = [n - (members[k - 1] if k else 0) for k, n in enumerate(members)]
    placed = [pieces.filter(F.col("length") > lo).select("pid", F.col("pid").alias("seq"), F.lit(0).cast("long").alias("offset"))]  # two of the first class don't fit together
    gaps = pieces.filter((F.col("length") > lo) & (F.col("length") < capacity)).select(F.col("pid").alias("seq"), (capacity - F.col("length")).alias("gap"))
    spark, opened, n_gaps = pieces.sparkSession, 1, members[0]  # -1 stands for no sequence
    for (lo, hi), n in zip(bounds[1:], members[1:]):
        left = pieces.filter((F.col("length") > lo) & (F.col("length") <= hi)).select("pid", "length")
        fresh = not n_gaps
        while n:
            if fresh:  # sequences for the pieces left, packed with their like
                need = left.agg(F.sum(F.lit(1.0) / F.floor(F.lit(capacity) / F.col("length")))).first()[0]
                more = max(1, int(need))
                gaps = gaps.union(spark.range(opened + 1, opened + more + 1).select((-F.col("id")).alias("seq"), F.lit(capacity).cast("long").alias("gap")))
                opened += more
                n_gaps += more
            able = gaps.filter(F.col("gap") > lo)
            swept = _sweep(left, able, lo, hi, n + n_gaps)
            counts = swept.groupBy("part").agg(F.count(F.when((F.col("kind") == PIECE) & (F.col("seq") == -1), 1)).alias("alone"), F.sum("slots").alias("slots"), F.count(F.when(F.col("kind") == GAP, 1)).alias("gaps")).collect()  # one row a range
            alone, slots = [0] * (1 + max(r["part"] for r in counts)), [0] * (1 + max(r["part"] for r in counts))
            for r in counts:
                alone[r["part"]], slots[r["part"]] = r["alone"], r["slots"]
            placed.append(swept.filter(f"kind = {PIECE} and seq <> -1").select(F.col("id").alias("pid"), "seq", (capacity - F.col("gap")).alias("offset")))
            now = swept.filter(f"kind = {GAP}").select(F.col("id").alias("seq"), F.col("size").alias("gap"))
            left = swept.filter(f"kind = {PIECE} and seq = -1").select(F.col("id").alias("pid"), F.col("size").alias("length"))
            n = sum(alone)
            rows, taken = deal(alone, slots)
            if len(rows):
                met = _dealt(swept, rows, taken, capacity)
                placed.append(met.select("pid", "seq", "offset"))
                now = now.join(met.select("seq").distinct(), "seq", "left_anti").union(met.groupBy("seq").agg(F.min("rest").alias("gap")).filter("gap > 0"))
                left = left.join(met.select("pid"), "pid", "left_anti")
                n -= int(rows[:, 2].sum())
            gaps = common.land(gaps.filter(F.col("gap") <= lo).union(now), "gaps")
            fresh = True
    out = placed[0]
    for p in placed[1:]:
        out = out.union(p)
    return out


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null and empty texts are one piece of the end id alone.  Rows that share a doc_id are packed as
    documents of their own; a null doc_id stays null.  Other columns aren't looked at.
    """
    pieces = cut_pieces(docs, path, capacity)
    at = place(pieces.select("pid", "length"), capacity)
    return pieces.join(at, "pid").select("doc_id", "piece", "start", "length", "ids_crc32", F.col("seq").alias("sequence_id"), "offset")


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(common.read(spark, sf_dir, "documents"))
