"""Quality of a text: histogram gradient-boosted trees over statistics of the document.

The trees are fitted on the driver from a bounded sample of labelled rows and flattened into arrays, which
numpy walks for a whole batch of documents and all trees at once. Statistics cover the whole text.

Results on odd input: null text is empty text and gets a score like any other; label rows without a label
or an id are left out, an id with several labels gets their majority (ties: good); without labels, or with
labels of one kind only, every score is the smoothed share of good labels; an empty table gives no rows;
further columns are not read.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import ship, slices

#: Labelled rows that a fit uses at most: those of the smallest hash of the id.
SAMPLE = 20_000
BINS = 64
MARKS = b".,;:!?*$#%&|=<>{}()[]\"'-_/\\@+~^`"
NAMES = (
    "log_bytes log_words log_lines word_bytes word_longest upper digit space mark other_bytes distinct_words top_word next_same distinct_lines line_words "
    "long_words upper_words capital_words bang star hash percent amp dollar pipe dot comma mark_end double_mark distinct_pairs"
).split()


def statistics(raw: bytes | None) -> list[float]:
    """Values of NAMES; all of them linear in the length of the text."""
    raw = raw or b""
    words, n = raw.split(), max(len(raw), 1)
    seen = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    w = max(len(words), 1)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    counts = Counter(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    first = Counter(x[0] for x in words)
    last = Counter(x[-1] for x in words)
    pairs = list(zip(words, words[1:]))
    of = lambda c: seen[ord(c)] / w
    letters = max(int(seen[65:91].sum() + seen[97:123].sum()), 1)
    return [
        np.log1p(len(raw)), np.log1p(len(words)), np.log1p(len(lines)), lengths.mean() if words else 0.0, float(lengths.max()) if words else 0.0,
        seen[65:91].sum() / letters, seen[48:58].sum() / n, (seen[32] + seen[9] + seen[10]) / n, seen[list(MARKS)].sum() / n, seen[128:].sum() / n,
        len(counts) / w, max(counts.values(), default=0) / w, sum(a == b for a, b in pairs) / w, len(set(lines)) / max(len(lines), 1), w / max(len(lines), 1),
        float((lengths > 14).sum()) / w, sum(x.isupper() for x in words) / w, sum(first[c] for c in range(65, 91)) / w,
        of("!"), of("*"), of("#"), of("%"), of("&"), of("$"), of("|"), of("."), of(","),
        sum(last[c] for c in b"!*#%&$") / w, sum(raw.count(x) for x in (b"!!", b"**", b"##", b"%%", b"&&", b"$$")) / w, len(set(pairs)) / max(len(pairs), 1),
    ]


class Forest:
    """Trees in flat arrays: node i splits on ``feature[i]`` at ``cut[i]`` (left: not above), a leaf points to itself."""

    def __init__(self, base, feature, cut, left, right, value, roots, depth):
        self.base, self.depth = float(base), int(depth)
        self.feature, self.left, self.right, self.roots = (np.asarray(x, np.int32) for x in (feature, left, right, roots))
        self.cut, self.value = np.asarray(cut, float), np.asarray(value, float)

    def score(self, x: np.ndarray) -> np.ndarray:
        if not len(self.roots) or not len(x):
            return np.full(len(x), 1 / (1 + np.exp(-self.base)))
        at = np.tile(self.roots, (len(x), 1))
        row = np.arange(len(x))[:, None]
        for _ in range(self.depth):
            at = np.where(x[row, self.feature[at]] <= self.cut[at], self.left[at], self.right[at])
        return 1 / (1 + np.exp(-(self.base + self.value[at].sum(axis=1))))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, rate: float = 0.15, ridge: float = 1.0, least: int = 5) -> Forest:
    """Logistic boosting over histograms of BINS quantile bins, level by level."""
    share = (y.sum() + 1) / (len(y) + 2)
    base = float(np.log(share / (1 - share)))
    flat: dict[str, list] = {k: [] for k in ("feature", "cut", "left", "right", "value")}
    roots: list[int] = []
    if len(y) == 0 or y.min() == y.max():
        return Forest(base, *flat.values(), roots, 0)
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS + 1)[1:-1])) for j in range(x.shape[1])]
    binned = np.stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(cuts)], 1)
    raw, many = np.full(len(y), base), x.shape[1]
    offset = np.arange(many) * BINS

    def leaf(v):
        i = len(flat["value"])
        for k, val in (("feature", 0), ("cut", np.inf), ("left", i), ("right", i), ("value", v)):
            flat[k].append(val)
        return i

    for _ in range(trees):
        p = 1 / (1 + np.exp(-raw))
        g, h = y - p, p * (1 - p)
        root = leaf(0.0)
        roots.append(root)
        open_nodes = [(root, np.arange(len(y)))]
        for _ in range(depth):
            below = []
            for node, rows in open_nodes:
                cell = (binned[rows] + offset).ravel()
                sums = [np.bincount(cell, np.repeat(v[rows], many), many * BINS).reshape(many, BINS).cumsum(1) for v in (g, h)]
                n = np.bincount(cell, minlength=many * BINS).reshape(many, BINS).cumsum(1)
                gl, hl = sums
                gt, ht = g[rows].sum(), h[rows].sum()
                gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
                gain[(n < least) | (len(rows) - n < least)] = -1
                j, b = np.unravel_index(int(gain.argmax()), gain.shape)
                if gain[j, b] <= 1e-9 or b >= len(cuts[j]):
                    continue
                to_left = binned[rows, j] <= b
                flat["feature"][node], flat["cut"][node] = int(j), float(cuts[j][b])
                for side, part in (("left", rows[to_left]), ("right", rows[~to_left])):
                    flat[side][node] = child = leaf(rate * g[part].sum() / (h[part].sum() + ridge))
                    below.append((child, part))
            open_nodes = below
        tree = Forest(0, *flat.values(), [root], depth)
        at = np.full(len(y), root)
        for _ in range(depth):
            at = np.where(x[np.arange(len(y)), tree.feature[at]] <= tree.cut[at], tree.left[at], tree.right[at])
        raw += tree.value[at]
    return Forest(base, *flat.values(), roots, depth)


def fit_on(docs: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", label: str = "quality", sample: int = SAMPLE, use: Column | None = None) -> Forest:
    """Fit on at most ``sample`` labelled rows (those that ``use`` admits, by hash of the id)."""
    ship(docs.sparkSession)
    known = labels.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(label).cast("double").alias("label")).where("doc_id is not null and label is not null")
    known = known.groupBy("doc_id").agg((F.avg("label") >= 0.5).cast("int").alias("label"))
    if use is not None:
        known = known.where(use)
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)  # bounded, so it may be broadcast
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("t")).join(F.broadcast(known), "doc_id")

    def work(batches):
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array([statistics(t) for t in b.column(1).to_pylist()], pa.list_(pa.float64()))], ["doc_id", "label", "x"])

    got = rows.mapInArrow(work, "doc_id long, label int, x array<double>").toPandas().sort_values("doc_id", kind="stable").drop_duplicates("doc_id")
    if not len(got):
        return fit(np.zeros((0, len(NAMES))), np.zeros(0))
    return fit(np.stack(got["x"].to_numpy()), got["label"].to_numpy(float))


def _quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def with_score(docs: DataFrame, forest: Forest, text: str = "text", score: str = "score", least: float | None = None) -> DataFrame:
    """The columns of ``docs`` and a last one with the score, which replaces one of its name; with ``least``, only rows that reach it, as they are."""
    ship(docs.sparkSession)
    if least is None:
        docs = docs.select(*(F.col(_quoted(c)) for c in docs.columns if c != score))
    names = docs.columns
    at = names.index(text)
    schema = StructType(docs.schema.fields + ([] if least is not None else [StructField(score, DoubleType())]))

    def work(batches):
        for b in slices(batches, 250):
            x = np.array([statistics(t.encode() if isinstance(t, str) else t) for t in b.column(at).to_pylist()])
            s = forest.score(x)
            out = pa.RecordBatch.from_arrays([*b.columns, *([pa.array(s)] if least is None else [])], schema.names)
            yield out if least is None else out.filter(pa.array(s >= least))

    # Plain names on the way in, for any name may be among the columns.
    return docs.toDF(*(f"c{i}" for i in range(len(names)))).mapInArrow(work, schema)


def auc(score: pd.Series, label: pd.Series) -> float:
    """Chance that a good row scores above a bad one; ties count half."""
    ranks = score.rank()
    good = label == 1
    n, m = int(good.sum()), int((~good).sum())
    return float((ranks[good].sum() - n * (n + 1) / 2) / (n * m)) if n and m else float("nan")
