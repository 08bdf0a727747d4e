"""What the operators of this folder share: written tables, code for workers, components of a graph."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The characters that separate words: space, tab, line feed, vertical tab, form feed, carriage return.
WORD = r"[^\x20\x09-\x0D]+"

_shipped: set[str] = set()


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a local one only where the session names none."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if found:
        return found
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir: driver and executors need a folder that they share")
    own = os.path.join("/tmp/checkpoints", f"lossband-{spark.sparkContext.applicationId}")
    os.makedirs(own, exist_ok=True)
    return f"file://{own}"


def ship(spark: SparkSession) -> None:
    """Give the workers this package, whatever their own path holds."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    top = Path(__file__).resolve().parents[1]
    out = os.path.join(tempfile.mkdtemp(prefix="lossband-"), f"{top.name}.zip")
    with zipfile.ZipFile(out, "w") as z:
        for p in sorted(top.rglob("*.py")):
            z.write(p, str(p.relative_to(top.parent)))
    spark.sparkContext.addPyFile(out)
    _shipped.add(app)


def slices(batches, rows: int = 100):
    """Short pieces of Arrow batches, so that a worker holds few texts as Python objects at a time."""
    for b in batches:
        for i in range(0, b.num_rows, rows):
            yield b.slice(i, rows)
        del b
        pa.default_memory_pool().release_unused()


class Scratch:
    """Tables written to the shared folder, so that a lost executor costs no lineage.

    A table that a later one replaces can be dropped; those that a result reads stay until ``clear``, or
    ``clear_all`` once everything that was built so far has been read.
    """

    made: list[Scratch] = []

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_dir(spark).rstrip('/')}/lossband-tables/{label}-{uuid.uuid4().hex[:12]}"
        self.paths: dict[int, tuple[DataFrame, str]] = {}
        self.n = 0
        Scratch.made.append(self)

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n:02d}-{name}"
        df.write.mode("overwrite").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)] = (out, path)  # the table is held, so that its id stays its own
        return out

    def drop(self, df: DataFrame) -> None:
        self._delete(self.paths.pop(id(df), (None, None))[1])

    def drop_all_but(self, *tables: DataFrame) -> None:
        """Of the tables that still stand, those that no result reads go."""
        for key in set(self.paths) - {id(t) for t in tables}:
            self._delete(self.paths.pop(key)[1])

    def clear(self) -> None:
        self._delete(self.root)

    @classmethod
    def clear_all(cls) -> None:
        """Delete all tables of this process; results not yet written or collected lose what they read."""
        while cls.made:
            cls.made.pop().clear()

    def _delete(self, path: str | None) -> None:
        if path:
            jvm, conf = self.spark._jvm, self.spark._jsc.hadoopConfiguration()
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(conf).delete(where, True)


def text_key(text: Column) -> Column:
    """What tells the texts of rows with the same id apart."""
    return F.xxhash64(text)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def connected_components(scratch: Scratch, edges: DataFrame) -> DataFrame:
    """(node, component) for every node of ``edges(a, b)``; the component is its smallest node.

    Alternates two steps that hang every neighbour on a smaller node (first the larger neighbours, then
    the smaller ones) until nothing moves. Each round is written to the shared folder; the driver sees a
    count and a checksum only. Self-loops and repeated edges are allowed; null ends are left out; no edge
    gives no row.
    """
    links = edges.where("a is not null and b is not null and a <> b").select(
        F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")
    ).distinct()
    links, before = scratch.keep(links, "links"), None
    while True:
        n, mark = links.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
        if (n, mark) == before or n == 0:
            break
        before = (n, mark)
        both = links.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(links.select("lo", "hi"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        least = large.groupBy("hi").agg(F.min("lo").alias("m"))
        moved = large.join(least, "hi").select(F.explode(F.array("hi", "lo")).alias("x"), "m")
        small = moved.where("x <> m").select(F.col("x").alias("hi"), F.col("m").alias("lo")).distinct()
        new = scratch.keep(small, "links")
        scratch.drop(links)
        links = new
    return links.groupBy("hi").agg(F.min("lo").alias("lo")).select(F.col("hi").alias("node"), F.col("lo").alias("component")).union(
        links.select(F.col("lo").alias("node"), F.col("lo").alias("component")).distinct()
    )
