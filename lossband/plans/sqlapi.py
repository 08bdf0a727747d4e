"""The methods in SQL: functions for losses and counts, a table function for windows, views over score tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Session functions in SQL; alpha is p / q.
FUNCTIONS = {
    "kept_windows": "(n BIGINT, p BIGINT, q BIGINT) RETURNS BIGINT RETURN greatest(1, (2 * p * n + q) div (2 * q))",
    "skipped_windows": "(n BIGINT, p BIGINT, q BIGINT) RETURNS BIGINT RETURN (n - greatest(1, (2 * p * n + q) div (2 * q))) div 2",
    "in_middle_cdf": "(n BIGINT, r BIGINT, p BIGINT, q BIGINT) RETURNS BOOLEAN RETURN (q - p) * n <= 2 * q * r AND 2 * q * r <= (q + p) * n",
    "pinball_loss": "(e DOUBLE, level DOUBLE) RETURNS DOUBLE RETURN greatest(level * e, (level - 1) * e)",
}


def register_functions(spark: SparkSession) -> None:
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")


def register_scores(scores: DataFrame, name: str = "scores") -> None:
    """Views ``scores`` and ``ranked`` of a score table."""
    from ..operators.rank import distributed

    scores.createOrReplaceTempView(name)
    distributed(scores).createOrReplaceTempView("ranked")


def select_central(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..queries.common import naive

    register_functions(spark)
    register_scores(naive(spark, sf_dir))
    return spark.sql(
        """SELECT source, series_id, origin FROM ranked
        WHERE rank_key > skipped_windows(n, :p, :q) AND rank_key <= skipped_windows(n, :p, :q) + kept_windows(n, :p, :q)""",
        args={"p": 4, "q": 5},
    )


@F.udtf(returnType="origin: bigint")
class WindowExplode:
    """Origins of the windows of one series, as a table function."""

    def eval(self, length: int, context: int, horizon: int, stride: int):
        for origin in range(0, length - context - horizon + 1, stride):
            yield (origin,)


def udtf_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..sources.tables import ship

    ship(spark)
    spark.udtf.register("window_explode", WindowExplode)
    return spark.sql("SELECT w.origin, s.series_id FROM VALUES ('a', 40), ('b', 30) AS s(series_id, length), LATERAL window_explode(s.length, 8, 4, 4) AS w")
