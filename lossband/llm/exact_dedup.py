"""Exact duplicates by a minimal perfect hash over historical distinct digests.

History is a table of its own, or, of one table, the upper half of its ids: where the largest id of a group
stays, no row below can win against them. Its distinct digests are split into shards by their bytes. Each
shard becomes one row: the bit arrays of a minimal perfect hash, and slots that hold the full digest, the
winner's id and the number of rows. Documents travel as (id, digest) to their shard, find a slot and compare
all 32 bytes: members are repeats of what the slot names. Those that are no members are grouped among
themselves.

Results on odd input: null text is empty text; a row without an id counts in its group and wins only
when no row has an id; rows that repeat an id and a text all carry the winning id; an empty table gives
no rows; further columns are not read.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, ship, slices, text_key

#: Rows of a lookup group and digests of a shard that are aimed at.
ROWS = 50_000
NO_ID = -(2**63)
LEVELS = 40
MASK = np.uint64(0xFFFFFFFFFFFFFFFF)


def normal(text: bytes | None) -> bytes:
    """Only A-Z change; null is empty."""
    return (text or b"").lower()


def _digest(batches):
    for b in slices(batches):
        yield pa.RecordBatch.from_arrays(
            [b.column(0), b.column(1), pa.array([hashlib.sha256(normal(t)).digest() for t in b.column(2).to_pylist()], pa.binary())], ["doc_id", "text_key", "digest"]
        )


def digests(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, text_key, digest) of every row; the key tells the texts of rows with one id and digest apart."""
    ship(docs.sparkSession)
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), text_key(F.col(text)).alias("text_key"), F.col(text).cast("binary").alias("t"))
    return rows.mapInArrow(_digest, "doc_id long, text_key long, digest binary")


# ---- the minimal perfect hash of one shard -------------------------------------------------------


def _words(raw: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(raw).view("<u8").reshape(len(raw), 4)


def _place(words: np.ndarray, level: int, size: int) -> np.ndarray:
    x = words[:, 1] ^ (words[:, 2] * np.uint64(2 * level + 1))
    x ^= x >> np.uint64(29)
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    return (x % np.uint64(size)).astype(np.int64)


def build_hash(raw: np.ndarray) -> tuple[list[int], bytes, np.ndarray]:
    """Level sizes, the levels' bits, and the order in which the n digests (n x 32 bytes) fill n slots."""
    words, left, sizes, bits, order = _words(raw), np.arange(len(raw)), [], [], []
    for level in range(LEVELS):
        if not len(left):
            break
        size = max(8, 2 * len(left))
        at = _place(words[left], level, size)
        alone = np.bincount(at, minlength=size) == 1
        hit = alone[at]
        order.append(left[hit][np.argsort(at[hit])])
        sizes.append(size)
        bits.append(alone)
        left = left[~hit]
    order.append(left)  # what no level could part is found by comparison
    flat = np.concatenate(bits) if bits else np.zeros(0, bool)
    return sizes, np.packbits(flat).tobytes(), np.concatenate(order) if order else left


def find(raw: np.ndarray, sizes, bits: bytes, slots: np.ndarray) -> np.ndarray:
    """Slot of each digest, or -1; a slot counts only if all its bytes are equal."""
    out = np.full(len(raw), -1, np.int64)
    flat = np.unpackbits(np.frombuffer(bits, np.uint8)).astype(bool)[: int(sum(sizes))]
    rank = np.cumsum(flat) - 1
    words, left, start = _words(raw), np.arange(len(raw)), 0
    for level, size in enumerate(sizes):
        at = _place(words[left], level, int(size)) + start
        hit = flat[at]
        slot = rank[at[hit]]
        same = (slots[slot] == raw[left[hit]]).all(axis=1)
        out[left[hit][same]] = slot[same]
        left, start = left[~hit], start + int(size)
    rest = int(flat.sum())
    for k in range(rest, len(slots)):
        out[left[(raw[left] == slots[k]).all(axis=1)]] = k
    return out


def _raw(column) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, 32)


def _build(key, t):
    raw = _raw(t.column("digest"))
    sizes, bits, order = build_hash(raw)
    take = lambda name: t.column(name).to_numpy().astype("<i8")[order].tobytes()
    return pa.table(
        {"shard": pa.array([key[0].as_py()], pa.int32()), "sizes": pa.array([sizes], pa.list_(pa.int64())), "bits": pa.array([bits], pa.binary()), "slots": pa.array([raw[order].tobytes()], pa.binary()), "winners": pa.array([take("winner")], pa.binary()), "counts": pa.array([take("n")], pa.binary())}
    )


def _lookup(key, rows, index):
    n = rows.num_rows
    winner, count, hit = np.full(n, NO_ID), np.zeros(n, np.int64), np.zeros(n, bool)
    if n and index.num_rows:
        at = find(_raw(rows.column("digest")), index.column("sizes")[0].as_py(), index.column("bits")[0].as_py(), np.frombuffer(index.column("slots")[0].as_py(), np.uint8).reshape(-1, 32))
        hit = at >= 0
        winner[hit] = np.frombuffer(index.column("winners")[0].as_py(), "<i8")[at[hit]]
        count[hit] = np.frombuffer(index.column("counts")[0].as_py(), "<i8")[at[hit]]
    return pa.table({"doc_id": rows.column("doc_id"), "text_key": rows.column("text_key"), "digest": rows.column("digest"), "hit": pa.array(hit), "winner": pa.array(winner, pa.int64(), mask=winner == NO_ID), "n": pa.array(count)})


# ---- the operator --------------------------------------------------------------------------------


def _grouped(rows: DataFrame) -> DataFrame:
    return rows.groupBy("digest").agg(F.coalesce(F.max("doc_id"), F.lit(NO_ID)).alias("winner"), F.count("*").alias("n"))


def _shard(shards: int):
    return F.pmod(F.xxhash64("digest"), F.lit(shards)).cast("int")


def build_index(scratch: Scratch, seen: DataFrame, shards: int) -> DataFrame:
    """One row per shard from ``seen(digest, winner, n)``, whose digests are distinct."""
    return scratch.keep(
        seen.withColumn("shard", _shard(shards)).groupBy("shard").applyInArrow(_build, "shard int, sizes array<long>, bits binary, slots binary, winners binary, counts binary"), "index"
    )


def look_up(rows: DataFrame, index: DataFrame, shards: int, total: int) -> DataFrame:
    """(doc_id, text_key, digest, hit, winner, n); a shard with many rows is looked up in several copies."""
    rows = rows.withColumn("shard", _shard(shards))
    aim = max(2_000, min(ROWS, total // shards))
    parts = rows.groupBy("shard").count().select("shard", F.ceil(F.col("count") / aim).cast("int").alias("parts"))  # at most one row a shard
    rows = rows.join(F.broadcast(parts), "shard").withColumn("part", F.pmod(F.xxhash64("doc_id", "shard"), F.col("parts")).cast("int"))
    index = index.join(F.broadcast(parts), "shard").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    return rows.drop("parts").groupBy("shard", "part").cogroup(index.groupBy("shard", "part")).applyInArrow(_lookup, "doc_id long, text_key long, digest binary, hit boolean, winner long, n long")


def exact_dedup(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", history: DataFrame | None = None) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, digest, text_key) for every row of ``docs``.

    The largest id of a group stays. With ``history`` (same columns) its rows win over those of ``docs``, and
    none of ``docs`` that they contain is kept; group sizes count the rows of both.
    """
    scratch = Scratch(docs.sparkSession, "exact")
    rows = scratch.keep(digests(docs, doc_id, text), "digests")
    if history is None:
        # Any cut gives the same rows; half of the ids balances the index and what is looked up.
        cut, total = rows.agg(F.percentile_approx("doc_id", 0.5), F.count("*")).first()
        late = F.coalesce(F.col("doc_id") >= F.lit(cut).cast("long"), F.lit(False))
        seen = _grouped(rows.where(late))
    else:
        late, total = F.lit(False), rows.count()
        seen = _grouped(digests(history, doc_id, text))
    seen = scratch.keep(seen, "seen")
    shards = max(16, math.ceil(seen.count() / ROWS))
    found = scratch.keep(look_up(rows, build_index(scratch, seen, shards), shards, total), "found")
    # What the index does not count: members of it that are not of it, and groups of nonmembers.
    fresh = found.where(~late).groupBy("digest", "hit").agg(F.count("*").alias("more"), F.max("doc_id").alias("own")).where("hit or more > 1")
    sizes = scratch.keep(fresh.select("digest", "more", "own"), "sizes")
    out = found.join(sizes, "digest", "left")
    winner = F.when(F.col("hit"), F.col("winner")).otherwise(F.coalesce("own", "doc_id"))
    size = F.when(F.col("hit"), F.col("n") + F.coalesce("more", F.lit(0))).otherwise(F.coalesce("more", F.lit(1)))
    kept = F.col("doc_id").eqNullSafe(winner) if history is None else ~F.col("hit") & F.col("doc_id").eqNullSafe(winner)
    scratch.drop_all_but(found, sizes)
    return out.select("doc_id", winner.alias("keep_id"), size.cast("long").alias("group_size"), kept.alias("kept"), "digest", "text_key")
