"""SentencePiece encoding and decoding by vectorised merge rounds.

The model file is read directly.  A text is marked and cut where no piece can reach across; words that
weren't seen yet are merged together in rounds (see merges): flat symbol arrays, the smallest pair rank
of each word, its occurrences merged from the left at the same time, compaction until no pair remains.
Symbols without a piece fall back to bytes.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .merges import PairTable, merge_words
from .tokencount import tokenizer_path

SPACE = "▁"
#: Piece types of the public model format.
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
MOST_CACHED = 300_000
LONGEST_CACHED = 64


class PieceModel:
    """A merge model with byte fallback and no rewriting of characters, encoded and decoded as its library does."""

    def __init__(self, path: str):
        from sentencepiece import sentencepiece_model_pb2

        spec = sentencepiece_model_pb2.ModelProto()
        with open(path, "rb") as f:
            spec.ParseFromString(f.read())
        norm = spec.normalizer_spec
        kinds = {p.type for p in spec.pieces}
        if spec.trainer_spec.model_type != 2 or norm.precompiled_charsmap or norm.remove_extra_whitespaces or not norm.escape_whitespaces or spec.trainer_spec.treat_whitespace_as_suffix or kinds & {USER_DEFINED, UNUSED} or not spec.trainer_spec.byte_fallback:
            raise ValueError("only merge models with byte fallback, plain normalisation and normal pieces are read")
        self.prefix = SPACE if norm.add_dummy_prefix else ""
        self.pieces = [p.piece for p in spec.pieces]
        self.types = [p.type for p in spec.pieces]
        self.normal = {p.piece: k for k, p in enumerate(spec.pieces) if p.type == NORMAL}
        self.byte_id = {int(p.piece[3:5], 16): k for k, p in enumerate(spec.pieces) if p.type == BYTE}
        self.id_byte = {k: b for b, k in self.byte_id.items()}
        self.unknown = next((k for k, t in enumerate(self.types) if t == UNKNOWN), None)
        # symbols: piece ids, then characters that only occur inside pieces; any other character is `other`
        self.symbol = dict(self.normal)
        for p in self.normal:
            for c in p:
                self.symbol.setdefault(c, len(self.pieces) + len(self.symbol))
        self.other = 2 * len(self.pieces) + len(self.symbol)
        order = {s: k for k, s in enumerate(sorted({-spec.pieces[i].score for i in self.normal.values()}))}
        pairs = {}
        for p, k in self.normal.items():
            for cut in range(1, len(p)):
                a, b = self.symbol.get(p[:cut]), self.symbol.get(p[cut:])
                if a is not None and b is not None:
                    pairs[a, b] = (order[-spec.pieces[k].score], k)
        self.table = PairTable(pairs)
        if any(SPACE in p.lstrip(SPACE) for p in self.normal):
            self.words = re.compile(r"[\s\S]+")
        elif any("\n" in p for p in self.normal if len(p) > 1):
            self.words = re.compile(rf"{SPACE}+[^{SPACE}]*|[^{SPACE}]+")
        else:
            self.words = re.compile(rf"\n|{SPACE}+[^{SPACE}\n]*|[^{SPACE}\n]+")
        self.cache: dict[str, list[int]] = {}

    def cut(self, text: str) -> list[str]:
        return self.words.findall(self.prefix + text.replace(" ", SPACE)) if text else []

    def _ids(self, words: list[str]) -> Iterator[list[int]]:
        for lo in range(0, len(words), 20_000):
            part = words[lo : lo + 20_000]
            get = self.symbol.get
            syms = []
            extra: dict[int, str] = {}
            for w in part:
                s = [get(c, -1) for c in w]
                if -1 in s:
                    for i, c in enumerate(w):
                        if s[i] < 0:
                            s[i] = self.other + ord(c)
                            extra[s[i]] = c
                syms.append(s)
            top = len(self.pieces)
            chars = {k: c for c, k in self.symbol.items() if k >= top} | extra
            for s in merge_words(syms, self.table):
                if max(s) >= top:
                    out: list[int] = []
                    for k in s:
                        out += [k] if k < top else [self.byte_id[b] for b in chars[k].encode("utf-8", "surrogatepass")]
                    s = out
                yield s

    def learn(self, words: set[str]) -> None:
        new = [w for w in words if w not in self.cache]
        self.cache.update(zip(new, self._ids(new)))

    def forget(self, words: set[str]) -> None:
        if len(self.cache) > MOST_CACHED:
            self.cache.clear()
        else:
            for w in [w for w in words if len(w) > LONGEST_CACHED]:
                self.cache.pop(w, None)

    def encode(self, texts: list[str]) -> list[list[int]]:
        cut = [self.cut(t) for t in texts]
        words = set().union(*cut)
        self.learn(words)
        get = self.cache.__getitem__
        out = [[i for ids in map(get, ws) for i in ids] for ws in cut]
        self.forget(words)
        return out

    def decode(self, ids: list[int]) -> str:
        """Pieces put together, byte pieces as UTF-8, marks as spaces, less the one that was put in front."""
        data = bytearray()
        first = True
        for i in ids:
            if i in self.id_byte:
                data.append(self.id_byte[i])
                first = False
                continue
            if self.types[i] == CONTROL:
                continue
            p = " ⁇ " if self.types[i] == UNKNOWN else self.pieces[i]
            if first and self.prefix and p.startswith(SPACE):
                p = p[1:]
            first = False
            data += p.replace(SPACE, " ").encode()
        return data.decode("utf-8", "replace")


_LOADED: dict[str, PieceModel] = {}


def encode_documents(docs: DataFrame, path: str | None = None) -> DataFrame:
    """Per row: doc_id, n_tokens, ids_sha256 (of decimal ids joined by commas), decoded_sha256.

    Whole texts; null and empty ones have no ids and decode to the empty string.  Rows are encoded one by
    one, so repeated ids, ties and other columns change nothing; doc_id may be null.
    path: a model file, at the same place on every machine.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        file = path or tokenizer_path("piece_bpe_32k.model")
        if file not in _LOADED:
            _LOADED[file] = PieceModel(file)
        model = _LOADED[file]
        told: dict[str, tuple[int, str, bytes]] = {}  # word: ids, ids as text, what they decode to
        sha = lambda x: hashlib.sha256(x).hexdigest()
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                cut = [model.cut(x or "") for x in part.column(1).to_pylist()]
                words = set().union(*cut)
                new = [w for w in words if w not in told]
                for w, ids in zip(new, model._ids(new)):
                    # with a control-free piece before it, a word decodes by itself; the text's first word is cut below
                    told[w] = (len(ids), ",".join(map(str, ids)), b"".join(bytes([model.id_byte[i]]) if i in model.id_byte else model.pieces[i].replace(SPACE, " ").encode() for i in ids))
                get = told.__getitem__
                n, by_ids, by_text = [], [], []
                for ws in cut:
                    found = list(map(get, ws))
                    n.append(sum(f[0] for f in found))
                    by_ids.append(sha(",".join([f[1] for f in found]).encode()))
                    data = b"".join([f[2] for f in found])
                    if model.prefix and ws and ws[0].startswith(SPACE):
                        data = data[1:]
                    by_text.append(sha(data.decode("utf-8", "replace").encode()))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n, pa.int64()), pa.array(by_ids, pa.string()), pa.array(by_text, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
                if len(told) > MOST_CACHED:
                    told.clear()
                else:
                    for w in new:
                        if len(w) > LONGEST_CACHED:
                            del told[w]

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op7_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(common.read(spark, sf_dir, "documents"))
