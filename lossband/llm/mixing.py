"""Mix sources to target weights: a min-cost flow over membership patterns, then seeded documents.

Documents that belong to the same sources form one pattern. Patterns offer their tokens once, twice and so
on, each further copy at a higher cost; sources ask for their quotas. The cheapest largest flow says how
many tokens each pattern gives. Where a source shares no document with another, that flow is its quota or
all it has, and Spark reckons it for any number of sources; the flow is solved on the driver for the
patterns of several sources and what they touch. A pattern's flow is some whole copies of all its documents
and a rest; the rest is spread over size classes and filled with documents in the order of a seeded hash,
never beyond it; what the classes leave open is closed with the next documents that fit, large ones first.

Results on odd input: null text or size counts as 0 words and is taken 0 times; a null source is a source
of its own, last in order; rows without an id are mixed like others; repeated rows are separate rows; an
empty table gives no rows; further columns are not read, those in ``keep`` are passed on.
"""

from __future__ import annotations

import heapq
import math
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, Scratch

#: Parts of the seeded order of one pattern and size class, and parts of each, that are summed before the cut is looked for.
PARTS = 256
#: Documents by pattern and size class that may close what is left open.
SPARE = 8


def source_order(name: str | None) -> tuple:
    """By code point, null last."""
    return (name is None, name or "")


def targets(sizes: dict, share: Fraction, weights=(5, 2, 1), most: int = 2) -> dict:
    """Target of each source: ``share`` of all sizes by cycling weights, none above ``most`` times its size."""
    names = sorted(sizes, key=source_order)
    weight = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    left, rest, out = set(names), share * sum(sizes.values()), {}
    while left:
        total = sum(weight[s] for s in left)
        want = {s: rest * weight[s] / Fraction(total) for s in left}
        full = [s for s in left if want[s] > most * sizes[s]]
        if not full:
            return out | want
        for s in full:
            out[s] = Fraction(most * sizes[s])
            rest -= out[s]
            left.discard(s)
    return out


def min_cost_flow(capacity: dict, quota: dict, most: int = 2) -> dict:
    """Tokens by (pattern, source): the largest flow, and of these one of least repetition cost.

    Pattern p (a tuple of sources) has ``most`` arcs of its capacity, the k-th at cost k * k, so that costs
    are convex. Shortest augmenting paths with potentials.
    """
    names = ["from", *(("p", p) for p in capacity), *(("s", s) for s in quota), "to"]
    at = {x: i for i, x in enumerate(names)}
    head: list[list[int]] = [[] for _ in names]
    to, room, cost = [], [], []

    def arc(a, b, c, w):
        for x, y, cc, ww in ((a, b, c, w), (b, a, 0, -w)):
            head[at[x]].append(len(to))
            to.append(at[y])
            room.append(cc)
            cost.append(ww)

    used = {}
    for p, c in capacity.items():
        for k in range(1, most + 1):
            arc("from", ("p", p), c, k * k)
        for s in p:
            used[p, s] = len(to)
            arc(("p", p), ("s", s), most * c, 0)
    for s, q in quota.items():
        arc(("s", s), "to", q, 0)
    start, goal, level = at["from"], at["to"], [0] * len(names)
    while True:
        far, by, heap = [None] * len(names), [-1] * len(names), [(0, start)]
        far[start] = 0
        while heap:
            d, x = heapq.heappop(heap)
            if d > far[x]:
                continue
            for e in head[x]:
                if room[e] > 0 and (far[to[e]] is None or d + cost[e] + level[x] - level[to[e]] < far[to[e]]):
                    far[to[e]], by[to[e]] = d + cost[e] + level[x] - level[to[e]], e
                    heapq.heappush(heap, (far[to[e]], to[e]))
        if far[goal] is None:
            break
        level = [v + (far[i] if far[i] is not None else far[goal]) for i, v in enumerate(level)]
        path, x = [], goal
        while x != start:
            path.append(by[x])
            x = to[by[x] ^ 1]
        push = min(room[e] for e in path)
        for e in path:
            room[e] -= push
            room[e ^ 1] += push
    return {k: room[e ^ 1] for k, e in used.items()}


def words(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", keep: list[str] | None = None) -> DataFrame:
    """(doc_id, size, sources, *keep): words of each text, and the one source as an array."""
    return docs.select(
        F.col(doc_id).cast("long").alias("doc_id"),
        F.coalesce(F.regexp_count(F.col(text).cast("string"), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
        F.array(F.col(source).cast("string")).alias("sources"), *(keep or []),
    )


def _by_weight(values: dict) -> Column:
    out = F.lit(None)
    for w, v in values.items():
        out = F.when(F.col("weight") == w, F.lit(v)).otherwise(out)
    return out


def source_targets(sizes: DataFrame, share: Fraction, weights=(5, 2, 1), most: int = 2) -> DataFrame:
    """``sizes(source, source_size)`` with (target, quota): as ``targets`` says, by sums over the sources alone.

    What a source of one unit of weight gets only grows while full sources leave, so a source that is full
    once stays so, and a round needs the sums of the full ones only.
    """
    nth = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))  # one row a source
    rows = sizes.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.pmod(nth - 1, F.lit(len(weights))) + 1).cast("int")))
    rows = rows.withColumn("source_size", F.col("source_size").cast("long"))
    total, weight = rows.agg(F.sum(F.col("source_size").cast("decimal(38,0)")), F.sum("weight")).first()
    unit, full = (Fraction(share) * int(total) / weight if weight else Fraction(0)), F.lit(False)
    while weight:
        #: The largest size of a source of each weight that its part exceeds ``most`` times.
        full = F.col("source_size") <= _by_weight({w: math.ceil(unit * w / most) - 1 for w in set(weights)})
        taken, left = rows.agg(F.sum(F.when(full, F.col("source_size").cast("decimal(38,0)"))), F.sum(F.when(~full, F.col("weight")))).first()
        now = (Fraction(share) * int(total) - most * int(taken or 0)) / left if left else unit
        if now == unit:
            break
        unit = now
    part = lambda kind: _by_weight({w: kind(unit * w) for w in set(weights)})
    target = F.when(full, (most * F.col("source_size")).cast("double")).otherwise(part(float))
    quota = F.when(full, most * F.col("source_size")).otherwise(part(math.floor))
    return rows.select("source", "source_size", target.cast("double").alias("target"), quota.cast("long").alias("quota"))


def _given(patterns: DataFrame, about: DataFrame, most: int) -> DataFrame:
    """(key, total, given): tokens that each pattern of ``patterns(key, sources, total)`` gives to its sources."""
    several = patterns.where(F.size("sources") > 1)
    of = patterns.withColumn("one", F.element_at("sources", 1)).join(about, F.col("one").eqNullSafe(F.col("source")))
    alone = of.withColumn("given", F.least("quota", most * F.col("total")))
    alone = alone.where(F.size("sources") == 1).select("key", "total", "given", "one")
    if several.isEmpty():
        return alone.drop("one")
    touched = several.select(F.explode("sources").alias("source")).distinct()
    mine = alone.join(touched, F.col("one").eqNullSafe(F.col("source")), "left_semi").select("key")
    solved = several.unionByName(patterns.join(mine, "key", "left_semi")).select("key", "sources", "total").collect()
    quota = {r["source"]: r["quota"] for r in about.join(touched.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s")), "left_semi").collect()}
    patterns_of = {tuple(sorted(r["sources"], key=source_order)): r for r in solved}
    flow = min_cost_flow({p: r["total"] for p, r in patterns_of.items()}, dict(sorted(quota.items(), key=lambda x: source_order(x[0]))), most)
    rows = [(r["key"], r["total"], sum(flow[p, s] for s in p)) for p, r in patterns_of.items()]
    return alone.join(mine, "key", "left_anti").drop("one").union(patterns.sparkSession.createDataFrame(rows, "key string, total long, given long"))


def mix(sized: DataFrame, share: Fraction = Fraction(3, 2), weights=(5, 2, 1), most: int = 2, seed: int = 7, quotas: dict | None = None, keep: list[str] | None = None):
    """Mix ``sized(doc_id, size, sources)``; ``quotas`` replaces the targets that weights give.

    Returns the rows (doc_id, size, sources, copies, taken, *keep) and the sources (source, source_size, target, quota).
    """
    spark, more = sized.sparkSession, keep or []
    scratch = Scratch(spark, "mix")
    size = F.coalesce(F.col("size"), F.lit(0)).cast("long")
    octave = F.when(F.col("size") > 0, F.floor(F.log2(F.col("size").cast("double")))).otherwise(-1).cast("int")
    rows = sized.select("doc_id", size.alias("size"), F.array_sort(F.array_distinct("sources")).alias("sources"), *more)
    rows = rows.withColumn("octave", octave).withColumn("h", F.xxhash64(F.coalesce("doc_id", F.lit(-1)), F.lit(seed))).withColumn("part", F.shiftrightunsigned("h", 48).cast("int"))
    rows = rows.withColumn("key", F.to_json(F.struct(F.col("sources").alias("s")))).withColumn("row", F.monotonically_increasing_id())
    rows = scratch.keep(rows, "sizes")
    sets = ["key", "octave"]
    sums = scratch.keep(rows.groupBy(*sets).agg(F.any_value("sources").alias("sources"), F.sum("size").alias("n")), "sums")
    patterns = sums.groupBy("key").agg(F.any_value("sources").alias("sources"), F.sum("n").alias("total"))
    patterns = scratch.keep(patterns.where(F.size("sources") > 0), "patterns")
    about = patterns.select(F.explode("sources").alias("source"), "total").groupBy("source").agg(F.sum("total").alias("source_size"))
    if quotas is None:
        about = source_targets(scratch.keep(about, "sources"), share, weights, most)
    else:
        asked = spark.createDataFrame([(s, float(q), int(q)) for s, q in quotas.items()], "s string, target double, quota long")
        about = about.join(asked, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    about = scratch.keep(about, "targets")
    # A pattern gives whole copies of all it has, and a rest that its size classes share.
    given = scratch.keep(_given(patterns, about, most), "given")
    big = lambda c: F.col(c).cast("decimal(19,0)")
    plan = sums.join(given, "key").where("total > 0").withColumn("rest", F.col("given") % F.col("total")).withColumn("product", big("rest") * big("n"))
    plan = scratch.keep(plan.select(*sets, F.expr("given div total").alias("whole"), "rest", F.expr("product div total").alias("quota")), "plan")
    # Where the seeded order reaches the quota: sums of parts first, then of the parts of one part, then the rows of that. The tables joined have one row
    # a pattern and size class, and their files' size tells Spark whether to broadcast them.
    def cut(summed: DataFrame, by: str) -> DataFrame:
        before = F.col("base") + F.coalesce(F.sum("sum").over(Window.partitionBy(*sets).orderBy(by).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        found = summed.withColumn("before", before).where("before <= quota")
        return found.groupBy(*sets).agg(F.max(by).alias("cut"), F.max("before").alias("before"))

    coarse = rows.withColumn("coarse", F.floor(F.col("part") / PARTS).cast("int")).groupBy(*sets, "coarse").agg(F.sum("size").alias("sum"))
    first = scratch.keep(cut(coarse.join(plan, sets).withColumn("base", F.lit(0).cast("long")), "coarse").join(plan, sets), "first-cut")
    within = rows.join(first.select(*sets, "cut", F.col("before").alias("base"), "quota"), sets).where(F.floor(F.col("part") / PARTS) == F.col("cut"))
    second = scratch.keep(cut(within.groupBy(*sets, "part").agg(F.sum("size").alias("sum"), F.max("base").alias("base"), F.max("quota").alias("quota")), "part").join(plan, sets), "second-cut")
    cuts = rows.join(second, sets, "left")
    edge = cuts.where("part = cut").withColumn("upto", F.col("before") + F.sum("size").over(Window.partitionBy(*sets).orderBy("h", "doc_id", "row")))
    edge = edge.withColumn("more", (F.col("upto") <= F.col("quota")).cast("int")).drop("upto")
    sure = cuts.where("cut is null or part <> cut").withColumn("more", F.coalesce((F.col("part") < F.col("cut")).cast("int"), F.lit(0)))
    picked = scratch.keep(sure.unionByName(edge).select("doc_id", "size", "sources", *more, *sets, "part", "h", "row", "whole", "more"), "picked")
    left = given.select("key", (F.col("given") % F.when(F.col("total") > 0, F.col("total"))).alias("rest")).join(picked.where("more = 1").groupBy("key").agg(F.sum("size").alias("got")), "key", "left")
    nth = F.row_number().over(Window.partitionBy(*sets).orderBy("part", "h", "doc_id", "row"))
    spare = picked.where("more = 0 and size > 0").withColumn("nth", nth).where(F.col("nth") <= SPARE)
    spare = spare.groupBy("key").agg(F.array_sort(F.collect_list(F.struct((-F.col("octave")).alias("big"), "nth", "size", "row"))).alias("spare"))  # at most SPARE a size class
    none = F.struct((F.col("rest") - F.coalesce("got", F.lit(0))).alias("open"), F.array().cast("array<long>").alias("rows"))
    take = lambda acc, x: F.when(x["size"] <= acc["open"], F.struct((acc["open"] - x["size"]).alias("open"), F.concat(acc["rows"], F.array(x["row"])).alias("rows"))).otherwise(acc)
    extra = spare.join(left.where("rest is not null"), "key").select(F.explode(F.aggregate("spare", none, take, lambda acc: acc["rows"])).alias("row"), F.lit(1).alias("also"))
    out = picked.join(scratch.keep(extra, "extra"), "row", "left")
    copies = F.when((F.col("size") > 0) & F.col("whole").isNotNull(), F.col("whole") + F.col("more") + F.coalesce("also", F.lit(0))).otherwise(0)
    out = out.withColumn("copies", copies.cast("int"))
    return out.select("doc_id", "size", "sources", "copies", (F.col("copies") * F.col("size")).cast("long").alias("taken"), *more), about
