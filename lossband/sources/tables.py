"""Readers and writers: the given tables, files of other formats, partitioned score tables, shards for a trainer."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give the workers this package, whatever their own path holds; once for each application."""
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


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, fmt: str, schema: str, path: str, **options) -> DataFrame:
    """A file of any of Spark's formats with its schema stated, so that nothing is read to infer it."""
    return spark.read.schema(schema).options(**options).format(fmt).load(path)


def register_views(spark: SparkSession, sf_dir: str, names=NAMES) -> None:
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names for written intermediate tables; one in /tmp only where none is named."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir: driver and executors need a folder that they share")
    own = f"/tmp/checkpoints/lossband-{spark.sparkContext.applicationId}"
    os.makedirs(own, exist_ok=True)
    return f"file://{own}"


def keep(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends there, and a lost executor loses nothing."""
    path = f"{shared_dir(df.sparkSession)}/lossband-tables/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def store_scores(scores: DataFrame, path: str) -> None:
    """One folder by reference and source, sorted by score, so that scans by threshold skip row groups."""
    scores.repartition("reference_id", "source", F.pmod(F.xxhash64("series_id"), F.lit(64))).sortWithinPartitions("rfl").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("reference_id", "source").parquet(path)


def load_scores(spark: SparkSession, path: str, reference_id: str | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    return df.where(F.col("reference_id") == reference_id) if reference_id else df


def write_shards(df: DataFrame, path: str, shards: int, rows_per_file: int = 1_000_000) -> None:
    """Windows for a trainer, dealt by hash of the series into ``shards`` parts."""
    df.repartition(shards, "source", "series_id").write.mode("overwrite").option("maxRecordsPerFile", rows_per_file).parquet(path)
