"""Exact retention ratios, and the schemas that stages hand to one another."""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: A window is named by its series and the slot in which its context begins.
KEY = ("source", "series_id", "origin")

OBSERVATION = T.StructType([T.StructField("source", T.StringType()), T.StructField("series_id", T.StringType()), T.StructField("t", T.LongType()), T.StructField("y", T.LongType())])
WINDOW_KEY = T.StructType([T.StructField("source", T.StringType()), T.StructField("series_id", T.StringType()), T.StructField("origin", T.LongType())])
SCORE = T.StructType([T.StructField("reference_id", T.StringType()), *WINDOW_KEY.fields, T.StructField("m", T.LongType()), T.StructField("rfl", T.DoubleType()), T.StructField("status", T.StringType())])


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """Check names and types of a stage's input; nullability is not part of it and no job runs."""
    have = dict(df.dtypes)
    for f in schema:
        if have.get(f.name) != f.dataType.simpleString():
            raise TypeError(f"column {f.name} is {have.get(f.name)}, not {f.dataType.simpleString()}")
    return df


@dataclass(frozen=True)
class Alpha:
    """Retention ratio num / den, above 0 and at most 1; kept as integers so that no cut depends on rounding."""

    num: int
    den: int

    def __post_init__(self):
        if not 0 < self.num <= self.den:
            raise ValueError("a retention ratio lies above 0 and is at most 1")

    @classmethod
    def of(cls, value) -> Alpha:
        """From an Alpha, a fraction, text, or a number of at most six decimals."""
        if isinstance(value, Alpha):
            return value
        exact = Fraction(str(value)) if isinstance(value, float) else Fraction(value)
        if isinstance(value, float) and (exact * 10**6).denominator != 1:
            raise ValueError("write a ratio of more than six decimals as a fraction")
        return cls(exact.numerator, exact.denominator)

    def kept(self, n: int) -> int:
        """Windows kept of n by the count rule: the nearest number, halves up, at least one."""
        return max(1, (2 * self.num * n + self.den) // (2 * self.den)) if n else 0

    def skipped(self, n: int) -> int:
        """Windows left out below the kept ones."""
        return (n - self.kept(n)) // 2

    def __str__(self):
        return f"{self.num}/{self.den}"
