"""Arrow UDFs, a grouped aggregate and a table function; ``register_all`` names them in SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gradsift.operators.hashing import HashFamily


@F.pandas_udf(T.FloatType())
def to_half(x: pd.Series) -> pd.Series:
    """Value after a round trip through IEEE half precision."""
    with np.errstate(over="ignore"):
        return pd.Series(x.to_numpy().astype(np.float16).astype(np.float32))


def sketch_agg(fam: HashFamily):
    """Grouped aggregate: packed sketch (row after row) of a group's updates."""

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def run(coord: pd.Series, delta: pd.Series) -> list:
        bucket, sign = fam.numpy(coord.to_numpy())
        rows = [np.bincount(b, weights=s * delta.to_numpy(), minlength=fam.cols) for b, s in zip(bucket, sign, strict=True)]
        return np.concatenate(rows).tolist()

    return run


def sketch_rows(fam: HashFamily):
    """Table function: the cells that one update touches."""

    @F.udtf(returnType="row int, bucket int, cell double")
    class SketchRows:
        def eval(self, coord: int, delta: float) -> Iterator[tuple[int, int, float]]:
            bucket, sign = fam.numpy(np.array([coord]))
            for r in range(fam.rows):
                yield r, int(bucket[r, 0]), float(sign[r, 0] * delta)

    return SketchRows


def register_all(spark: SparkSession, fam: HashFamily) -> None:
    """sketch_rows(coord, delta), sketch_agg(coord, delta), to_half(x) and the view ``hashes``."""
    spark.udtf.register("sketch_rows", sketch_rows(fam))
    spark.udf.register("sketch_agg", sketch_agg(fam))
    spark.udf.register("to_half", to_half)
    fam.frame(spark).createOrReplaceTempView("hashes")
