"""Count Sketch over DataFrames: build, merge, query.

``cells`` frames have columns row, bucket, cell (and optional group columns).  Building is one
aggregation on (row, bucket): partial sums run before the exchange, so a map task never ships
more than rows * cols records however many updates it reads.  Integer deltas give integer cells,
for which linearity holds bit for bit.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gradsift.operators.hashing import HashFamily

#: Cells (doubles) that are packed into one broadcast row at most; larger sketches are joined.
PACKED_CELLS = 8_000_000


def validate_deltas(df: DataFrame, field: int, delta: str = "delta") -> DataFrame:
    """Raises on null, negative or too large coordinates and on NaN; drops zero deltas."""
    c, d = F.col("coord"), F.col(delta)
    bad = c.isNull() | (c < 0) | (c >= field) | d.isNull()
    if dict(df.dtypes)[delta] in ("double", "float"):
        bad = bad | F.isnan(d)
    checked = F.when(bad, F.raise_error(F.lit("coordinate or delta out of range"))).otherwise(d)
    return df.withColumn(delta, checked).where(F.col(delta) != 0)


def to_fixed(df: DataFrame, scale: int, column: str = "delta") -> DataFrame:
    """Exact mode: deltas as scaled 64-bit integers (overflow raises)."""
    return df.withColumn(column, F.round(F.col(column) * F.lit(scale)).cast("long"))


def sketch(df: DataFrame, fam: HashFamily, by: list[str] | None = None, delta: str = "delta") -> DataFrame:
    """Cells of the updates df(coord, delta), per group of ``by`` if given."""
    by = by or []
    spread = df.select(*by, F.col(delta).alias("_d"), F.inline(fam.cells_of(F.col("coord"))))
    return spread.groupBy(*by, "row", "bucket").agg(F.sum(F.col("_d") * F.col("sign")).alias("cell"))


def sketch_blocks(df: DataFrame, fam: HashFamily, by: str | None = None) -> DataFrame:
    """Cells by a numpy kernel: each Arrow batch is summed with bincount before the exchange."""
    key = [by] if by else []
    kind = "long" if dict(df.dtypes)["delta"] == "bigint" else "double"

    def run(frames):
        for pdf in frames:
            for k, part in pdf.groupby(by) if by else [(None, pdf)]:
                bucket, sign = fam.numpy(part["coord"].to_numpy())
                d = part["delta"].to_numpy()
                for r in range(fam.rows):
                    if kind == "long":
                        cell = np.zeros(fam.cols, np.int64)
                        np.add.at(cell, bucket[r], sign[r] * d)
                    else:
                        cell = np.bincount(bucket[r], weights=sign[r] * d, minlength=fam.cols)
                    at = np.unique(bucket[r])
                    out = {"row": np.full(len(at), r, np.int32), "bucket": at.astype(np.int32), "cell": cell[at]}
                    yield pd.DataFrame(({by: k} if by else {}) | out)

    schema = f"{f'{by} int, ' if by else ''}row int, bucket int, cell {kind}"
    cells = df.select(*(F.col(c).cast("int") for c in key), "coord", "delta").mapInPandas(run, schema)
    return cells.groupBy(*key, "row", "bucket").agg(F.sum("cell").alias("cell"))


def merge(cells: DataFrame, how: str = "sum", workers: int | None = None, by: list[str] | None = None) -> DataFrame:
    """Sum of sketches (or their mean over ``workers``): the only exchange, rows * cols per worker."""
    out = cells.groupBy(*(by or []), "row", "bucket").agg(F.sum("cell").alias("cell"))
    if how == "mean":
        return out.withColumn("cell", F.col("cell") / F.lit(float(workers)))
    if how != "sum":
        raise ValueError("how is 'sum' or 'mean'")
    return out


def scale(cells: DataFrame, a: float | int) -> DataFrame:
    return cells.withColumn("cell", F.col("cell") * F.lit(a))


def subtract(a: DataFrame, b: DataFrame) -> DataFrame:
    return merge(a.unionByName(scale(b, -1)))


def packed_rows(cells: DataFrame, fam: HashFamily) -> DataFrame:
    """(row, cells): one array of all cols for each sketch row, empty buckets zero."""
    every = cells.sparkSession.range(fam.rows * fam.cols).select(F.expr(f"cast(id div {fam.cols} as int)").alias("row"), F.expr(f"cast(id % {fam.cols} as int)").alias("bucket"))
    full = every.join(cells.select("row", "bucket", "cell"), ["row", "bucket"], "left").select("row", "bucket", F.coalesce(F.col("cell").cast("double"), F.lit(0.0)).alias("cell"))
    lists = full.groupBy("row").agg(F.sort_array(F.collect_list(F.struct("bucket", "cell"))).alias("x"))
    return lists.select("row", F.col("x.cell").alias("cells"))


def packed_row(cells: DataFrame, fam: HashFamily) -> DataFrame:
    """One row with the whole sketch as an array of arrays; its size is fixed by the family and checked."""
    if fam.rows * fam.cols > PACKED_CELLS:
        raise ValueError("sketch too large to pack; join on (row, bucket) instead")
    return packed_rows(cells, fam).agg(F.sort_array(F.collect_list(F.struct("row", "cells"))).alias("x")).select(F.col("x.cells").alias("_table"))


def packed(cells: DataFrame, fam: HashFamily) -> np.ndarray:
    """The whole sketch as a rows by cols array on the driver; its size is fixed by the family."""
    if fam.rows * fam.cols > PACKED_CELLS:
        raise ValueError("sketch too large to pack; join on (row, bucket) instead")
    out = np.zeros((fam.rows, fam.cols))
    rows = packed_rows(cells, fam).toArrow()
    for r, x in zip(rows.column("row").to_pylist(), rows.column("cells").combine_chunks(), strict=True):
        out[r] = x.values.to_numpy()
    return out


def estimate(cells: DataFrame, fam: HashFamily, coords: DataFrame) -> DataFrame:
    """(coord, est): median over rows of signed cells, for the coordinates given.

    Within the packed size the sketch is one broadcast row: each coordinate looks its cells up in a
    projection, and nothing is shuffled.  A larger sketch joins on (row, bucket).
    """
    if fam.rows * fam.cols <= PACKED_CELLS:
        x, r = F.col("coord"), fam.rows
        signed = [F.get(F.get(F.col("_table"), F.lit(i)), fam.bucket(x, i)) * fam.sign(x, i) for i in range(r)]
        order = F.sort_array(F.array(*signed))
        middle = F.get(order, F.lit(r // 2))
        if r % 2 == 0:
            middle = (F.get(order, F.lit(r // 2 - 1)) + middle) / 2
        table = F.broadcast(packed_row(cells, fam))
        return coords.select("coord").crossJoin(table).select("coord", (middle + F.lit(0.0)).alias("est"))
    asked = coords.select("coord", F.inline(fam.cells_of(F.col("coord"))))
    value = F.col("sign") * F.coalesce(F.col("cell"), F.lit(0))
    return asked.join(cells.select("row", "bucket", "cell"), ["row", "bucket"], "left").groupBy("coord").agg(F.median(value.cast("double")).alias("est"))


def estimate_all(cells: DataFrame, fam: HashFamily, d: int, kernel: str = "sql") -> DataFrame:
    """Estimates of all coordinates below d; ``numpy`` uses the packed sketch per Arrow batch."""
    spark = cells.sparkSession
    coords = spark.range(d).withColumnRenamed("id", "coord")
    if kernel == "sql":
        return estimate(cells, fam, coords)
    table = packed(cells, fam)

    def run(frames):
        for pdf in frames:
            x = pdf["coord"].to_numpy()
            bucket, sign = fam.numpy(x)
            yield pd.DataFrame({"coord": x, "est": np.median(sign * np.take_along_axis(table, bucket, 1), axis=0)})

    return coords.mapInPandas(run, "coord long, est double")


def row_norms(cells: DataFrame) -> DataFrame:
    """(row, norm2): the squared norm as each sketch row sees it (integer cells: summed exactly)."""
    kind = "decimal(19,0)" if dict(cells.dtypes)["cell"] == "bigint" else "double"
    square = F.col("cell").cast(kind) * F.col("cell").cast(kind)
    return cells.groupBy("row").agg(F.sum(square).cast("double").alias("norm2"))


def norm2(cells: DataFrame) -> DataFrame:
    """One row: the estimated squared norm, median over rows."""
    return row_norms(cells).agg(F.median("norm2").alias("norm2"))


def heavy_hitters(cells: DataFrame, fam: HashFamily, d: int, eps: float) -> DataFrame:
    """Coordinates whose squared estimate exceeds eps times the estimated squared norm."""
    est = estimate_all(cells, fam, d)
    return est.crossJoin(F.broadcast(norm2(cells))).where(F.col("est") * F.col("est") > F.lit(eps) * F.col("norm2")).select("coord", "est")


def by_size(value: str) -> list[Column]:
    """Order of selection everywhere: larger magnitude first, then smaller coordinate."""
    return [F.abs(F.col(value)).desc(), F.col("coord").asc()]


def approx_top_k(cells: DataFrame, fam: HashFamily, d: int, k: int) -> DataFrame:
    return estimate_all(cells, fam, d).orderBy(*by_size("est")).limit(k)


def size_for(k: int, d: int, delta: float, steps: int = 1, c_rows: float = 1.0, c_cols: float = 4.0) -> tuple[int, int]:
    """(rows, cols) for top-k recovery with failure probability delta over ``steps`` steps.

    Rows grow with log(d * steps / delta), columns with k; the constants are ours.
    """
    rows = max(1, math.ceil(c_rows * math.log(d * steps / delta)))
    return rows + 1 - rows % 2, max(1, math.ceil(c_cols * k))


def quantise(cells: DataFrame, bits: int = 16, mode: str = "scaled", seed: int = 0) -> DataFrame:
    """16-bit cells: ``half`` (IEEE half precision), or integers scaled by the largest cell,
    rounded to ``scaled`` (nearest) or ``stochastic`` (seeded by the cell's place)."""
    if mode == "half":
        from gradsift.functions.udfs import to_half

        return cells.withColumn("code", to_half(F.col("cell").cast("double"))).drop("cell")
    top = 2 ** (bits - 1) - 1
    step = cells.agg((F.max(F.abs("cell")) / top).cast("double").alias("step"))
    q = F.col("cell") / F.when(F.col("step") > 0, F.col("step")).otherwise(F.lit(1.0))
    if mode == "scaled":
        code = F.round(q)
    elif mode == "stochastic":
        u = F.pmod(F.xxhash64("row", "bucket", F.lit(seed)), F.lit(1 << 30)) / F.lit(float(1 << 30))
        code = F.floor(q + u)
    else:
        raise ValueError("mode is 'half', 'scaled' or 'stochastic'")
    code = F.greatest(F.least(code, F.lit(top)), F.lit(-top)).cast("short")
    return cells.crossJoin(F.broadcast(step)).withColumn("code", code).drop("cell")


def dequantise(codes: DataFrame) -> DataFrame:
    if "step" in codes.columns:
        return codes.withColumn("cell", F.col("code") * F.col("step")).drop("code", "step")
    return codes.withColumnRenamed("code", "cell")
