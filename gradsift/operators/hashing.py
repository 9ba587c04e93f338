"""Seeded hash family of a Count Sketch: degree-3 polynomials over a prime field.

A row has two polynomials: one gives the bucket, one the sign.  All products stay below 2**62, so
64-bit integer arithmetic is exact in Spark (where overflow raises) and in any SQL engine.
"""

from __future__ import annotations

import random
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

FIELD = 2**31 - 1


@dataclass(frozen=True)
class HashFamily:
    """``rows`` pairs of polynomials; coordinates must lie in [0, field)."""

    rows: int
    cols: int
    seed: int = 42
    field: int = FIELD

    @property
    def coefficients(self) -> list[tuple[tuple[int, ...], tuple[int, ...]]]:
        rnd = random.Random(self.seed)
        pick = lambda: tuple([rnd.randrange(1, self.field), *(rnd.randrange(self.field) for _ in range(3))])
        return [(pick(), pick()) for _ in range(self.rows)]

    def frame(self, spark: SparkSession) -> DataFrame:
        """hashes(row, b3..b0, s3..s0), one row per sketch row."""
        names = [f"{k}{i}" for k in "bs" for i in (3, 2, 1, 0)]
        schema = T.StructType([T.StructField("row", T.IntegerType(), False), *(T.StructField(n, T.LongType(), False) for n in names)])
        return spark.createDataFrame([(r, *b, *s) for r, (b, s) in enumerate(self.coefficients)], schema)

    def _value(self, x: Column, coef) -> Column:
        out = F.lit(coef[0]).cast("long")
        for c in coef[1:]:
            out = (out * x + F.lit(c).cast("long")) % F.lit(self.field).cast("long")
        return out

    def bucket(self, x: Column, row: int) -> Column:
        return (self._value(x, self.coefficients[row][0]) % self.cols).cast("int")

    def sign(self, x: Column, row: int) -> Column:
        return F.lit(1) - F.lit(2) * (self._value(x, self.coefficients[row][1]) % 2)

    def cells_of(self, x: Column) -> Column:
        """array<struct<row, bucket, sign>> of a coordinate; constants are folded into the plan."""
        return F.array(
            *(F.struct(F.lit(r).alias("row"), self.bucket(x, r).alias("bucket"), self.sign(x, r).cast("long").alias("sign")) for r in range(self.rows))
        )

    def numpy(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(buckets, signs), each rows by len(x)."""
        x = x.astype(np.int64)

        def value(coef):
            out = np.full(len(x), coef[0], np.int64)
            for c in coef[1:]:
                out = (out * x + c) % self.field
            return out

        pairs = [(value(b) % self.cols, 1 - 2 * (value(s) % 2)) for b, s in self.coefficients]
        return np.array([p[0] for p in pairs]), np.array([p[1] for p in pairs])

    # the same arithmetic as SQL text, for engines that check the result
    def _sql(self, x: str, coef) -> str:
        out = f"{coef[0]}::BIGINT"
        for c in coef[1:]:
            out = f"(({out} * {x} + {c}) % {self.field})"
        return out

    def sql_cells(self, source: str, x: str = "coord", keep: str = "*") -> str:
        """SELECT with row, bucket and sign added, one branch per sketch row."""
        return " UNION ALL ".join(
            f"SELECT {keep}, {r} AS row, CAST({self._sql(x, b)} % {self.cols} AS INTEGER) AS bucket, 1 - 2 * ({self._sql(x, s)} % 2) AS sign FROM {source}"
            for r, (b, s) in enumerate(self.coefficients)
        )
