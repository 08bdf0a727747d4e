"""Near duplicates by an inverted join of MinHash signature coordinates.

A document is its set of distinct word shingles; documents of equal sets are one class. Every class has a
signature of COORDINATES minima and is posted under each (coordinate, value). Two classes can be linked only
if they collide in MATCHES lists or more, so lists with one class are skipped, and so are classes with fewer
than MATCHES coordinates in shared lists. The pairs of a group are never listed:

1. Every list names as representative the class whose own lists hold most posts, which is the one in the middle
   of a group. In one order of representatives, the one with most posts first, a class keeps the leading ones
   until fewer than MATCHES of its lists are left (a prefix): two classes that collide often enough then have the
   first representative of their common lists in both prefixes.
2. Each class is compared with the representatives of its prefix on full sets. That gives links, components,
   and for each such pair what the two sets do not share. Lists that lie within one component are skipped from
   here on; classes that still have MATCHES coordinates in lists of several components are open. A group can
   have many members beside its representative's reach, each linked with many within it; so each open class
   is compared with one class of every list it is in, whose signature agrees as a link's would, and the
   components and the open classes are found once more. This only saves pairs: what it misses stays open.
3. Open classes near the same representative are posted under what tells them from it. If two sets differ from
   it in A and B, they differ from one another in A + B without what A and B share, so a link between
   different components needs a known part of A and B to be the same: prefixes of A and B, rarest first, and
   the places of the shared part bound the pairs, and texts that only share their template never meet.
4. Open classes far from a representative are merged on signatures: the prefix of their coordinates, shortest
   lists first, is joined, a pair is met at its first common list only, collisions in the skipped long lists
   are counted from the signatures, and pairs with MATCHES go on.
5. Pairs of steps 3 and 4 are confirmed on full sets.

Near and far overlap by the distance that a link may have, so by the triangle inequality a linked pair is met
in step 3 or in step 4. A link of similarity 0.85 collides in fewer than MATCHES of COORDINATES with a chance
below 1e-6; nothing else loses one.

Results on odd input: null text, empty text and text without words have an empty set, are linked with
nothing and are their own component; fewer words than a shingle are one shingle; a row without an id is
its own group (no component, kept); rows that repeat an id are one document of several texts, so what is
linked with one of them is linked with all, in whatever order the rows come; an empty table gives no rows;
further columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, connected_components, ship, slices, text_key

COORDINATES, MATCHES = 32, 16
#: Similarity to a representative, in percent, from which a class counts as near.
NEAR = 20
WORDS_KNOWN = 150_000

_seeds = np.random.default_rng(20).integers(1, 2**63, (2, COORDINATES), dtype=np.uint64) | np.uint64(1)


class _Words(dict):
    def __missing__(self, word):
        if len(self) > WORDS_KNOWN:
            self.clear()
        self[word] = found = xxhash.xxh3_64_intdigest(word)
        return found


_known = _Words()


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def shingles(raw: bytes | None, size: int) -> np.ndarray:
    """Sorted 64-bit hashes of the distinct shingles of ``size`` words; ASCII letters are lower-cased."""
    words = (raw or b"").lower().split()
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(_known.__getitem__, words), np.uint64, n)
    size = min(size, n)
    out = np.full(n - size + 1, size, np.uint64)
    for j in range(size):
        out = _mix(out * np.uint64(0x9E3779B97F4A7C15) + h[j : n - size + 1 + j])
    return np.unique(out)


def signature(hashes: np.ndarray) -> np.ndarray:
    """Minimum of each coordinate, the coordinate's number in its lowest bits."""
    low = np.full(COORDINATES, 0xFFFFFFFFFFFFFFFF, np.uint64)
    for i in range(0, len(hashes), 4096):
        part = hashes[i : i + 4096, None]
        x = (part ^ _seeds[0]) * _seeds[1]
        x ^= x >> np.uint64(31)
        np.minimum(low, x.min(axis=0), out=low)
    return (low & ~np.uint64(127)) | np.arange(COORDINATES, dtype=np.uint64)


def _lists(arrays: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, arrays)])
    flat = np.concatenate(arrays) if arrays else np.zeros(0, np.uint64)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat.view(np.int64)))


def _sets(size: int, full: bool):
    """Full sets of (id, text), or sizes, marks and signatures of (doc, key, text)."""

    def work(batches):
        for part in slices(batches):
            sets = [shingles(t, size) for t in part.column(part.num_columns - 1).to_pylist()]
            if full:
                yield pa.RecordBatch.from_arrays([part.column(0), _lists(sets)], ["id", "hashes"])
                continue
            n = pa.array([len(s) for s in sets], pa.int64())
            marks = pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], pa.binary())
            signs = _lists([signature(s) if len(s) else np.zeros(0, np.uint64) for s in sets])
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), n, marks, signs], ["doc", "key", "n", "mark", "sign"])

    return work


def _overlap(x: np.ndarray, y: np.ndarray) -> int:
    return len(x) + len(y) - len(np.union1d(x, y))


def _confirm(percent: int):
    """Of pairs with their full sets: those with enough overlap."""

    def work(batches):
        for b in slices(batches, 500):
            ha, hb, keep = b.column(2), b.column(3), []
            for i in range(b.num_rows):
                x, y = ha[i].values.to_numpy(), hb[i].values.to_numpy()
                both = _overlap(x, y)
                keep.append(100 * both >= percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return work


def _compare(percent: int):
    """Of pairs of a class and a representative: sizes, link or not, near or far, and for near ones what one set has and the other lacks."""

    def work(batches):
        for b in slices(batches, 500):
            ha, hb, out, differ = b.column(2), b.column(3), [], []
            for i in range(b.num_rows):
                x, y = ha[i].values.to_numpy(), hb[i].values.to_numpy()
                both = _overlap(x, y)
                of = len(x) + len(y) - both
                near = 100 * both >= NEAR * of
                out.append((len(x), len(y), 100 * both >= percent * of, near, 100 * both < (NEAR + 100 - percent) * of))
                differ.append(np.setxor1d(x, y, assume_unique=True).view(np.uint64) if near else np.zeros(0, np.uint64))
            n, m, link, near, far = zip(*out) if out else [()] * 5
            cols = [b.column(0), b.column(1), pa.array(n, pa.int64()), pa.array(m, pa.int64()), *(pa.array(v, pa.bool_()) for v in (link, near, far)), _lists(differ)]
            yield pa.RecordBatch.from_arrays(cols, ["id", "rep", "n", "m", "link", "near", "far", "differ"])

    return work


def _with_sets(pairs: DataFrame, sets: DataFrame, a: str, b: str) -> DataFrame:
    left = sets.select(F.col("id").alias(a), F.col("hashes").alias("ha"))
    right = sets.select(F.col("id").alias(b), F.col("hashes").alias("hb"))
    return pairs.select(a, b).join(left, a).join(right, b).select(a, b, "ha", "hb")


def _several(posts: DataFrame, of: Column, matches: int) -> DataFrame:
    """(id, token, ..., weight) of the lists that hold more than one ``of``, for ids with at least ``matches`` of them; the weight is the number of posts in an id's lists."""
    spread = posts.groupBy("token").agg(F.min(of).alias("lo"), F.max(of).alias("hi"), F.count("*").alias("posts")).where("lo <> hi").select("token", "posts")
    left = posts.join(spread, "token")
    of_id = left.groupBy("id").agg(F.count("*").alias("lists"), F.sum("posts").alias("weight")).where(F.col("lists") >= matches)
    return left.drop("posts").join(of_id.drop("lists"), "id")


def _prefixes(shared: DataFrame, matches: int) -> DataFrame:
    """(id, rep): the representatives of step 1 that each class is compared with."""
    named = shared.groupBy("token").agg(F.max(F.struct("weight", (-F.col("id")).alias("less"))).alias("best")).select("token", F.col("best.weight").alias("first"), (-F.col("best.less")).alias("rep"))
    votes = shared.join(named, "token").groupBy("id", "rep", "first").agg(F.count("*").alias("votes"))
    rest = F.sum("votes").over(Window.partitionBy("id").orderBy(F.desc("first"), "rep").rowsBetween(Window.currentRow, Window.unboundedFollowing))
    return votes.withColumn("rest", rest).where((F.col("rest") >= matches) & (F.col("id") != F.col("rep"))).select("id", "rep")


def _places(rows: DataFrame, group: list[str], least: Column) -> DataFrame:
    """``rows`` with one row for each token in several sets of its group, and its place among the set's tokens, rarest first, down to the last place that matters."""
    flat = rows.withColumn("token", F.explode("differ")).drop("differ")
    often = flat.groupBy(*group, "token").agg(F.count("*").alias("df")).where("df > 1")
    # Tokens of one set only fill the first places and need no row.
    flat, own = flat.join(often, [*group, "token"]), Window.partitionBy(*group, "id")
    place = F.col("d") - F.count("*").over(own) + F.row_number().over(own.orderBy("df", "token"))
    return flat.withColumn("place", place).where(F.col("place") <= F.col("d") - least + 1)


def _likely_pairs(open_posts: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """(a, b): each class of ``open_posts`` with one class of every list of its own, another one in each list, if it lies in another component and their signatures agree about as often as a link's do."""
    signs = classes.select("id", "sign")
    named = open_posts.groupBy("token").agg(F.min_by("id", F.xxhash64("id", "token")).alias("id"))
    # A class is named in no more lists than it has, so only the join by list can meet a hot key, as in step 1.
    named = named.join(signs, "id").join(open_posts.select("id", "comp").distinct(), "id").select("token", F.col("id").alias("b"), F.col("comp").alias("other"), F.col("sign").alias("theirs"))
    agree = F.size(F.array_intersect("sign", "theirs")) >= COORDINATES * percent // 100 - 1
    return open_posts.join(signs, "id").join(named, "token").where((F.col("comp") != F.col("other")) & agree).select(F.col("id").alias("a"), "b").distinct()


def _near_pairs(met: DataFrame, open_ids: DataFrame, percent: int, scratch: Scratch) -> DataFrame:
    """(a, b): step 3. ``e`` and ``k`` are such that a pair needs 2 * (100 + percent) tokens for each e1 + e2, and a class is linked with the representative if e <= k."""
    unit = 2 * (100 + percent)
    rows = met.where("near").join(open_ids, "id").select("rep", "id", "comp", "link", F.size("differ").cast("long").alias("d"), "n", "m", "differ")
    rows = rows.withColumn("e", (100 + percent) * F.col("d") - (100 - percent) * F.col("n")).withColumn("k", (100 - percent) * F.col("m")).drop("n", "m")
    # Against a class that is not linked with the representative (one of a pair is not, or both are in its component), and against any.
    tight, loose = F.floor((F.col("e") + F.col("k")) / unit) + 1, F.greatest(F.lit(1), F.ceil((F.col("e") - F.col("k")) / unit))
    placed = scratch.keep(_places(rows, ["rep"], F.when(F.col("link"), tight).otherwise(loose)).withColumn("last", F.col("d") - tight + 1).drop("df", "k"), "differences")
    one = placed.where("place <= last").select("rep", "token", *(F.col(c).alias(f"{c}1") for c in ("id", "comp", "link", "d", "e", "place")))
    two = placed.where("not link").select("rep", "token", *(F.col(c).alias(f"{c}2") for c in ("id", "comp", "d", "e", "place")))
    # All that two sets share comes at or after the first token they share.
    most = F.least(F.col("d1") - F.col("place1"), F.col("d2") - F.col("place2")) + 1
    meets = (F.col("comp1") != F.col("comp2")) & (F.col("link1") | (F.col("id1") < F.col("id2"))) & (unit * most >= F.col("e1") + F.col("e2"))
    return one.join(two, ["rep", "token"]).where(meets).select(F.col("id1").alias("a"), F.col("id2").alias("b")).distinct()


def _far_pairs(met: DataFrame, open_ids: DataFrame, shared: DataFrame, matches: int, scratch: Scratch) -> DataFrame:
    """(a, b): step 4."""
    posts = shared.select("id", "token").join(met.where("far").select("id").distinct(), "id").join(open_ids, "id")
    posts = posts.join(posts.groupBy("token").agg(F.count("*").alias("df")).where("df > 1"), "token")
    lists = posts.groupBy("id", "comp").agg(F.array_sort(F.collect_list(F.struct("df", "token"))).alias("by")).where(F.size("by") >= matches)  # at most COORDINATES a class
    lists = lists.select("id", "comp", F.transform("by", lambda x: x["token"]).alias("tokens")).withColumn("prefix", F.slice("tokens", 1, F.size("tokens") - matches + 1))
    rows = scratch.keep(lists.withColumn("token", F.explode("prefix")), "prefixes")
    one, two = (rows.select("token", *(F.col(c).alias(f"{c}{i}") for c in ("id", "comp", "tokens", "prefix"))) for i in (1, 2))
    first = F.element_at(F.array_intersect("prefix1", "prefix2"), 1) == F.col("token")
    meets = (F.col("id1") < F.col("id2")) & (F.col("comp1") != F.col("comp2")) & first & (F.size(F.array_intersect("tokens1", "tokens2")) >= matches)
    return one.join(two, "token").where(meets).select(F.col("id1").alias("a"), F.col("id2").alias("b"))


def _one_document(usable: DataFrame, classes: DataFrame) -> DataFrame:
    """(a, b): links between the classes of rows that repeat an id."""
    several = usable.groupBy(F.col("doc").alias("of")).agg(F.min("mark").alias("lo"), F.max("mark").alias("hi")).where("lo <> hi").select("of", "lo")
    pairs = usable.select("doc", "mark").join(several, usable["doc"] == several["of"]).where("mark <> lo").select("lo", "mark").distinct()
    ids = classes.select("id", "mark")
    return pairs.join(ids.select(F.col("id").alias("a"), F.col("mark").alias("lo")), "lo").join(ids.withColumnRenamed("id", "b"), "mark").select("a", "b")


def near_dedup(docs: DataFrame, size: int = 5, percent: int = 80, matches: int | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, kept, text_key, mark) of every row; ``mark`` is that of its set; links are sets with 100 * overlap >= percent * union."""
    spark = docs.sparkSession
    ship(spark)
    scratch = Scratch(spark, "near")
    matches = matches or max(1, MATCHES - round((85 - percent) * COORDINATES / 100))
    rows = docs.select(F.col(doc_id).cast("long").alias("doc"), text_key(F.col(text)).alias("key"), F.col(text).cast("binary").alias("t"))
    signed = scratch.keep(rows.mapInArrow(_sets(size, False), "doc long, key long, n long, mark binary, sign array<long>"), "signed")
    usable = signed.where("n > 0 and doc is not null")
    # Classes are numbered, and the numbers fixed by writing them.
    classes = usable.groupBy("mark").agg(F.min(F.struct("doc", "key")).alias("least"), F.any_value("sign").alias("sign")).select("mark", "least.*", "sign")
    classes = scratch.keep(classes.withColumn("id", F.monotonically_increasing_id()), "classes")
    posts = scratch.keep(classes.select("id", F.explode("sign").alias("token")), "posts")
    shared = scratch.keep(_several(posts, F.col("id"), matches), "shared")
    scratch.drop(posts)

    wanted = classes.join(shared.select("id").distinct(), "id", "left_semi").select("id", F.col("doc").alias("of"), F.col("key").alias("kind"))
    full = rows.join(wanted, (rows["doc"] == wanted["of"]) & (rows["key"] == wanted["kind"])).select("id", "t").mapInArrow(_sets(size, True), "id long, hashes array<long>")
    sets = scratch.keep(full.dropDuplicates(["id"]), "sets")
    met = _with_sets(_prefixes(shared, matches), sets, "id", "rep").mapInArrow(_compare(percent), "id long, rep long, n long, m long, link boolean, near boolean, far boolean, differ array<long>")
    met = scratch.keep(met, "met")
    same = _one_document(usable, classes)
    joined = scratch.keep(connected_components(scratch, met.where("link").select(F.col("id").alias("a"), F.col("rep").alias("b")).union(same)), "joined")

    def still_open(joined: DataFrame) -> DataFrame:
        at = shared.select("id", "token").join(joined, shared["id"] == joined["node"], "left").select("id", "token", F.coalesce("component", "id").alias("comp"))
        return _several(at, F.col("comp"), matches).select("id", "token", "comp")

    def confirmed(pairs: DataFrame) -> DataFrame:
        return scratch.keep(_with_sets(pairs, sets, "a", "b").mapInArrow(_confirm(percent), "a long, b long"), "links")

    def with_links(joined: DataFrame, links: DataFrame) -> DataFrame:
        return connected_components(scratch, links.union(joined.select(F.col("node").alias("a"), F.col("component").alias("b"))))

    likely = scratch.keep(_likely_pairs(scratch.keep(still_open(joined), "open_posts"), classes, percent), "likely")
    joined = scratch.keep(with_links(joined, confirmed(likely)), "joined")
    open_ids = scratch.keep(still_open(joined).select("id", "comp").distinct(), "open")
    pairs = scratch.keep(_near_pairs(met, open_ids, percent, scratch).union(_far_pairs(met, open_ids, shared, matches, scratch)).distinct(), "pairs")
    found = with_links(joined, confirmed(pairs))

    # The smallest document of each component, for the classes that are in one.
    of = found.join(classes.select("id", "doc"), found["node"] == F.col("id")).select("id", "component", "doc")
    of = of.join(of.groupBy("component").agg(F.min("doc").alias("component_id")), "component").select("id", "component_id")
    groups = scratch.keep(classes.select("id", "mark", "doc").join(of, "id", "left").select("mark", F.coalesce("component_id", "doc").alias("component_id")), "groups")
    scratch.drop_all_but(signed, groups)
    grouped = usable.join(groups, "mark", "left").select("doc", "key", "n", "component_id", "mark")
    # Rows without a set or an id would all meet in one task of that join, and need no partner.
    alone = signed.where("n = 0 or doc is null").select("doc", "key", "n", F.col("doc").alias("component_id"), "mark")
    out = grouped.union(alone)
    return out.select(F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), "component_id", F.coalesce(F.col("doc") == F.col("component_id"), F.lit(True)).alias("kept"), F.col("key").alias("text_key"), "mark")
