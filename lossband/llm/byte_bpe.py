"""Byte-level BPE: exact merges in linear time, and decoding.

Every byte becomes one Latin-1 character, so that an Aho-Corasick automaton over the vocabulary finds
all tokens of a piece in one pass. A piece is then covered from the left by its longest token; a token is
accepted if it and the one before it are what merging their joined bytes yields (memoised), otherwise the
next shorter token is tried, and a position from which nothing fits is never entered again. A sequence
whose neighbours are all compatible is the one that the merges give.

Results on odd input: null text is empty text; the empty text has no ids; rows repeat as they come; an
empty table gives no rows; further columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
from functools import cached_property

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship, slices

#: Entries that a worker's memo of pieces or of pairs may hold before it starts afresh.
MEMO = 400_000


class _Memo(dict):
    def __init__(self, make):
        self.make = make

    def __missing__(self, key):
        if len(self) >= MEMO:
            self.clear()
        self[key] = found = self.make(key)
        return found


class ByteBPE:
    """Encoder and decoder of one rank file (lines of base64 token and rank)."""

    def __init__(self, ranks: bytes, pattern: str):
        self.rank = {base64.b64decode(a): int(b) for a, b in (x.split() for x in ranks.splitlines() if x.strip())}
        self.split = regex.compile(pattern).findall
        self.token = {i: t for t, i in self.rank.items()}
        self.ids_of = _Memo(self._piece)
        self.fits = _Memo(lambda pair: self.merge(pair[0] + pair[1]) == list(pair))

    def merge(self, piece: bytes) -> list[bytes]:
        """The definition: join the neighbours of lowest rank, leftmost first, until none is left."""
        parts, none = [piece[i : i + 1] for i in range(len(piece))], len(self.rank) + 1
        while len(parts) > 1:
            ranks = [self.rank.get(a + b, none) for a, b in zip(parts, parts[1:])]
            best = min(ranks)
            if best == none:
                break
            at = ranks.index(best)
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    @cached_property
    def automaton(self) -> ahocorasick.Automaton:
        """Of the tokens that merging can reach."""
        out = ahocorasick.Automaton()
        for t in self.rank:
            if self.merge(t) == [t]:
                out.add_word(t.decode("latin-1"), len(t))
        out.make_automaton()
        return out

    def cover(self, piece: bytes) -> list[bytes]:
        size = len(piece)
        lengths: list[list[int]] = [[] for _ in range(size)]
        for end, n in self.automaton.iter(piece.decode("latin-1")):
            lengths[end + 1 - n].append(n)
        # For each position, the lengths not tried yet; ascending, so that the longest is popped first.
        dead, tokens, at = bytearray(size + 1), [], 0
        tried: list[list[int]] = [sorted(lengths[0])] if size else []
        while at < size:
            while tried[-1]:
                n = tried[-1].pop()
                token = piece[at : at + n]
                if not dead[at + n] and (not tokens or self.fits[tokens[-1], token]):
                    tokens.append(token)
                    at += n
                    tried.append(sorted(lengths[at]) if at < size else [])
                    break
            else:
                dead[at] = 1
                tried.pop()
                if not tokens:
                    raise ValueError("the vocabulary lacks a byte")
                at -= len(tokens.pop())
        return tokens

    def _piece(self, piece: str) -> bytes:
        raw = piece.encode()
        whole = self.rank.get(raw)
        found = [whole] if whole is not None else [self.rank[t] for t in self.cover(raw)]
        return np.array(found, "<u4").tobytes()

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.ids_of.__getitem__, self.split(text)))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.token.__getitem__, np.frombuffer(ids, "<u4").tolist()))


_loaded: dict[str, ByteBPE] = {}


def load(ranks: bytes, pattern: str) -> ByteBPE:
    """One per worker process and vocabulary."""
    key = hashlib.sha256(ranks + pattern.encode()).hexdigest()
    if key not in _loaded:
        _loaded.clear()
        _loaded[key] = ByteBPE(ranks, pattern)
    return _loaded[key]


def encode_table(docs: DataFrame, ranks_path: str, pattern: str, doc_id: str = "doc_id", text: str = "text", ids: bool = True) -> DataFrame:
    """(doc_id, n_tokens, ids, ids_sha256, decoded_sha256, exact); ``ids`` packed, left out if not asked for.

    ``exact`` says whether decoding gave the bytes of the text back. The rank file is read on the driver
    and broadcast: its size is that of one vocabulary.
    """
    spark = docs.sparkSession
    ship(spark)
    with open(ranks_path, "rb") as f:
        ranks = spark.sparkContext.broadcast(f.read())

    def work(batches):
        bpe = load(ranks.value, pattern)
        for b in slices(batches):
            out = []
            for t in b.column(1).to_pylist():
                packed = bpe.encode(t := t or "")
                back = bpe.decode(packed)
                out.append((len(packed) // 4, packed, hashlib.sha256(packed).hexdigest(), hashlib.sha256(back).hexdigest(), back == t.encode()))
            n, packed, a, c, same = zip(*out) if out else [()] * 5
            cols = [b.column(0), pa.array(n, pa.int64()), pa.array(packed, pa.binary()), pa.array(a, pa.string()), pa.array(c, pa.string()), pa.array(same, pa.bool_())]
            if not ids:
                del cols[2]
            yield pa.RecordBatch.from_arrays(cols, names)

    names = [x for x in ("doc_id", "n_tokens", "ids", "ids_sha256", "decoded_sha256", "exact") if ids or x != "ids"]
    kinds = {"doc_id": "long", "n_tokens": "long", "ids": "binary", "ids_sha256": "string", "decoded_sha256": "string", "exact": "boolean"}
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("t"))
    return rows.mapInArrow(work, ", ".join(f"{x} {kinds[x]}" for x in names))


def decode_table(encoded: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """(doc_id, text) back from (doc_id, ids)."""
    spark = encoded.sparkSession
    ship(spark)
    with open(ranks_path, "rb") as f:
        ranks = spark.sparkContext.broadcast(f.read())

    def work(batches):
        bpe = load(ranks.value, pattern)
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([bpe.decode(x or b"").decode("utf-8", "replace") for x in b.column(1).to_pylist()], pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(work, "doc_id long, text string")
