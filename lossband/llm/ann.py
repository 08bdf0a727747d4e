"""Nearest neighbours by multiprobe p-stable hashing.

Equal vectors are one index row with their smallest ids. Inner products become distances by one more
coordinate, which lifts every vector to the norm of the longest; queries get a zero there. Each of several
tables cuts the line of a few Gaussian projections into cells. A query visits, in every table, its own
cell and then those that perturbing single projections reaches, in the order of the estimated chance that
a near vector lies there; the tables' candidates are merged and ranked by exact inner products.

How many cells a query visits, and how many hashes a table has, follow from recall that is measured before
the search: some of the queries are answered by brute force over all vectors, and the visits at which the
tables would meet those answers are counted. Visits are raised, then hashes taken away, until the share met
is large enough; a table without hashes is one cell, so the last resort is brute force for all queries.

The rows of a cell and the queries that visit it are cut into blocks of bounded size, which meet as one matrix
product; only the best of a block leave it.

Results on odd input: vectors that are null, empty, zero or hold null or non-finite components take no
part, nor do rows without an id; vectors of different length never meet; a repeated id is a further row; no
vector or no query gives no rows; further columns are not read.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, ship

#: Rows of which the spread of projections is taken; the index holds all rows.
SAMPLE = 4_096
#: Index rows of one block, at most.
BLOCK = 4_096
#: Queries answered by brute force over all vectors, the share of their answers that visits must meet, and
#: the visits a table beyond which hashes are taken away instead.
FIT = 128
FIT_RECALL = 0.95
MOST_PROBES = 64


class Tables:
    """Projections of ``tables`` tables of ``bits`` hashes each, and how far queries probe."""

    def __init__(self, dim: int, top: float, spread: float, tables: int, bits: int, probes: int, width: float, seed: int):
        rng = np.random.default_rng([seed, dim])
        self.a = rng.standard_normal((tables, bits, dim + 1))
        self.width = width * max(spread, 1e-12)
        self.b = rng.uniform(0, 1, (tables, bits)) * self.width
        self.top, self.probes = float(top), probes

    def lift(self, x: np.ndarray, query: bool) -> np.ndarray:
        rest = np.zeros(len(x)) if query else np.sqrt(np.maximum(self.top**2 - (x**2).sum(1), 0))
        return np.hstack([x, rest[:, None]])

    def places(self, x: np.ndarray, query: bool) -> np.ndarray:
        """rows x tables x bits, in units of a cell."""
        return (np.einsum("nd,tkd->ntk", self.lift(x, query), self.a) + self.b) / self.width

    @staticmethod
    def key(cells: np.ndarray) -> np.ndarray:
        """64 bits of each row of integers."""
        out = np.full(cells.shape[:-1], 0x9E3779B97F4A7C15, np.uint64)
        for j in range(cells.shape[-1]):
            out ^= cells[..., j].astype(np.int64).view(np.uint64)
            out *= np.uint64(0xBF58476D1CE4E5B9)
            out ^= out >> np.uint64(29)
        return out.view(np.int64)

    def visits(self, place: np.ndarray) -> list[np.ndarray]:
        """Cells for one query and table: its own, then by the sum of squared distances to the borders crossed.

        Grows sets of steps from the smallest: shift the last step to the next one, or add the next one;
        a set that moves one projection both ways is passed over.
        """
        own = np.floor(place)
        if not len(own):
            return [own]
        frac = place - own
        steps = sorted([(f * f, j, -1) for j, f in enumerate(frac)] + [((1 - f) ** 2, j, 1) for j, f in enumerate(frac)])
        out, heap = [own], [(steps[0][0], (0,))]
        while heap and len(out) < self.probes:
            cost, chosen = heapq.heappop(heap)
            if len({steps[i][1] for i in chosen}) == len(chosen):
                cell = own.copy()
                for i in chosen:
                    cell[steps[i][1]] += steps[i][2]
                out.append(cell)
            last = chosen[-1]
            if last + 1 < len(steps):
                heapq.heappush(heap, (cost - steps[last][0] + steps[last + 1][0], (*chosen[:-1], last + 1)))
                heapq.heappush(heap, (cost + steps[last + 1][0], (*chosen, last + 1)))
        return out


def clean(vectors: DataFrame, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """(id, v) of the rows that take part, v as doubles."""
    rows = vectors.select(F.col(vec_id).cast("long").alias("id"), F.col(embedding).cast("array<double>").alias("v"))
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return rows.where(F.col("id").isNotNull() & F.col("v").isNotNull() & finite & F.exists("v", lambda x: x != 0))


def _matrix(column) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return np.stack(column.to_numpy(zero_copy_only=False)).astype(float)


def _best(ids: np.ndarray, q: np.ndarray, reps: np.ndarray, x: np.ndarray, k: int) -> pa.Table:
    """(query, rep, score) of the k + 1 best of ``x`` for every query, and of all that tie with the last of them."""
    out = [(ids[:0], reps[:0], np.zeros(0))]
    for i in range(0, len(ids), 512):
        s = q[i : i + 512] @ x.T
        if s.shape[1] > k + 1:
            # Everything that ties with the last of the best stays, for ties go by id.
            least = np.partition(s, s.shape[1] - k - 1, axis=1)[:, s.shape[1] - k - 1]
            row, col = np.nonzero(s >= (least - 1e-12 * np.abs(least))[:, None])
        else:
            row, col = np.nonzero(np.ones_like(s, bool))
        out.append((ids[i + row], reps[col], s[row, col]))
    a, b, c = (np.concatenate(z) for z in zip(*out))
    return pa.table({"query": a.astype(np.int64), "rep": b.astype(np.int64), "score": c})


def _exact(met: DataFrame, asked: DataFrame, base: DataFrame, k: int) -> DataFrame:
    """(query, score, vec_id, rep, rank): exact ranking of the met pairs on the original vectors."""
    best = met.groupBy("query", "rep").agg(F.max("score").alias("rough"))
    order = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("rough"), "rep"))
    best = best.withColumn("nth", order).where(F.col("nth") <= 2 * k + 2).drop("nth", "rough")
    q = asked.select(F.col("id").alias("query"), F.col("v").alias("qv")).distinct()
    dot = F.aggregate(F.zip_with("qv", "v", lambda a, b: a * b), F.lit(0.0), lambda acc, x: acc + x)
    exact = best.join(q, "query").join(base.select("rep", "v", "ids"), "rep").select("query", "rep", dot.alias("score"), F.explode("ids").alias("vec_id")).where("query <> vec_id")
    rank = F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "vec_id"))
    return exact.withColumn("rank", rank).where(F.col("rank") <= k)


def _answers(base: DataFrame, asked: DataFrame, dim: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Queries of one length, and brute force answers to them: the query's row and the vector of each answer."""
    own = asked.where(F.col("dim") == dim)
    some = own.groupBy("id").agg(F.min("v").alias("v")).orderBy(F.xxhash64("id")).limit(FIT).toPandas()
    if not len(some):
        return np.zeros((0, dim)), np.zeros(0, int), np.zeros((0, dim))
    ids, q = some["id"].to_numpy(), np.stack(some["v"].to_numpy()).astype(float)

    def scan(batches):
        for b in batches:
            if b.num_rows:
                yield from _best(ids, q, b.column(0).to_numpy(), _matrix(b.column(1)), k).to_batches()

    rows = base.where(F.col("dim") == dim)
    met = rows.select("rep", "v").mapInArrow(scan, "query long, rep long, score double")
    few = base.sparkSession.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, q)], "id long, v array<double>")
    found = _exact(met, F.broadcast(few), rows, k).select("query", "rep").join(rows.select("rep", "v"), "rep").select("query", "v").toPandas()
    at = {i: n for n, i in enumerate(ids)}
    return q, np.array([at[i] for i in found["query"]], int), np.stack(found["v"].to_numpy()).astype(float) if len(found) else np.zeros((0, dim))


def _met_at(model: Tables, q: np.ndarray, row: np.ndarray, x: np.ndarray) -> np.ndarray:
    """For each answer, the number of visits to every table after which one of them has met it; infinite if none does."""
    place, keys = model.places(q, True), Tables.key(np.floor(model.places(x, False)))
    out = np.full(len(row), np.inf)
    for i in range(len(q)):
        mine = np.flatnonzero(row == i)
        for t in range(place.shape[1]):
            nth = {c: n + 1 for n, c in reversed(list(enumerate(Tables.key(np.array(model.visits(place[i, t]))).tolist())))}
            out[mine] = np.minimum(out[mine], [nth.get(c, np.inf) for c in keys[mine, t].tolist()])
    return out


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 20, tables: int = 4, bits: int | None = None, probes: int | None = None, width: float = 2.25, seed: int = 11, vec_id: str = "vec_id", embedding: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the ``k`` rows of largest inner product found, not counting the query's own.

    ``bits`` starts from the logarithm of the number of different vectors unless given, and ``probes`` from
    ``bits``; measured recall raises the one and lowers the other. ``width`` of a cell is in spreads of a
    projection.
    """
    spark = vectors.sparkSession
    ship(spark)
    scratch = Scratch(spark, "ann")
    nth = F.row_number().over(Window.partitionBy("v").orderBy("id"))
    # The limit by group also holds before the shuffle, so equal vectors send k + 1 rows a task.
    few = clean(vectors, vec_id, embedding).withColumn("nth", nth).where(F.col("nth") <= k + 1)
    base = scratch.keep(few.groupBy("v").agg(F.min("id").alias("rep"), F.array_sort(F.collect_list("id")).alias("ids")).withColumn("dim", F.size("v")), "base")
    asked = scratch.keep(clean(queries, vec_id, embedding).withColumn("dim", F.size("v")), "asked")
    # By length of vector: how many, and the largest norm. One row for each length that occurs.
    stats = base.groupBy("dim").agg(F.count("*").alias("n"), F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)).alias("top")).collect()
    models = {}
    for r in stats:
        sample = base.where(F.col("dim") == r["dim"]).orderBy(F.xxhash64("rep")).limit(SAMPLE).select("v").toPandas()["v"]
        x = np.stack(sample.to_numpy()).astype(float)
        m = max(1, round(math.log2(max(r["n"], 2) / 600))) if bits is None else bits
        model = Tables(r["dim"], math.sqrt(r["top"]), 1.0, tables, max(m, 1), 1, 1.0, seed)
        spread = float((np.einsum("nd,tkd->ntk", model.lift(x, False), model.a)).std()) if len(x) else 1.0
        q, row, answers = _answers(base, asked, r["dim"], k)
        while True:
            least = probes or max(16, 6 * m)
            # Without hashes every table is the same one cell.
            model = Tables(r["dim"], math.sqrt(r["top"]), spread, tables if m else 1, m, max(least, MOST_PROBES), width, seed)
            at = np.sort(_met_at(model, q, row, answers))
            need = at[math.ceil(FIT_RECALL * len(at)) - 1] if len(at) else 1
            if need <= model.probes:
                break
            m -= 1
        model.probes = max(least, int(need))
        models[r["dim"]] = model

    def index(batches):
        for b in batches:
            dims = b.column(2).to_numpy()
            for d in np.unique(dims):
                part = b.filter(pa.array(dims == d))
                at = models[int(d)].places(_matrix(part.column(1)), False)
                keys = Tables.key(np.floor(at))
                n, t = keys.shape
                take = pa.array(np.repeat(np.arange(n), t))
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(dims[dims == d], t), pa.int32()), pa.array(np.tile(np.arange(t), n), pa.int32()), pa.array(keys.ravel()), part.column(0).take(take), part.column(1).take(take)], ["dim", "tab", "cell", "id", "v"])

    def probe(batches):
        for b in batches:
            dims = b.column(2).to_numpy()
            for d in np.unique(dims):
                if int(d) not in models:
                    continue
                part, model = b.filter(pa.array(dims == d)), models[int(d)]
                at = model.places(_matrix(part.column(1)), True)
                rows = [(i, t, c) for i in range(len(at)) for t in range(at.shape[1]) for c in model.visits(at[i, t])]
                keys = Tables.key(np.array([c for *_, c in rows]))
                take = pa.array([i for i, *_ in rows])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(rows), d), pa.int32()), pa.array([t for _, t, _ in rows], pa.int32()), pa.array(keys), part.column(0).take(take), part.column(1).take(take)], ["dim", "tab", "cell", "id", "v"])

    shape = "dim int, tab int, cell long, id long, v array<double>"
    posted = scratch.keep(base.select(F.col("rep").alias("id"), "v", "dim").mapInArrow(index, shape), "posted")
    cells = ["dim", "tab", "cell"]
    # Blocks of a cell: rows are dealt by hash, so that a cell of any size is met in bounded parts.
    # Its queries are dealt likewise, and every block of rows meets every block of queries.
    visits = scratch.keep(asked.select("id", "v", "dim").mapInArrow(probe, shape), "visits")
    blocks_of = lambda rows, name: rows.groupBy(*cells).count().select(*cells, F.ceil(F.col("count") / BLOCK).cast("int").alias(name))
    sizes = scratch.keep(blocks_of(posted, "blocks").join(blocks_of(visits, "asks"), cells), "cells")
    dealt = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    posted = posted.join(sizes, cells).withColumn("block", dealt("blocks")).withColumn("ask", each("asks")).drop("blocks", "asks")
    visits = visits.join(sizes, cells).withColumn("ask", dealt("asks")).withColumn("block", each("blocks")).drop("blocks", "asks")

    def meet(key, have, want):
        empty = pa.table({"query": pa.array([], pa.int64()), "rep": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        if not have.num_rows or not want.num_rows:
            return empty
        return _best(want.column("id").to_numpy(), _matrix(want.column("v")), have.column("id").to_numpy(), _matrix(have.column("v")), k)

    met = posted.groupBy(*cells, "block", "ask").cogroup(visits.groupBy(*cells, "block", "ask")).applyInArrow(meet, "query long, rep long, score double")
    return _exact(met, asked, base, k).select(F.col("query").alias("query_id"), F.col("rank").cast("int").alias("rank"), "vec_id", "score")
