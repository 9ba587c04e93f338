"""Sharding along a Hilbert curve, in DataFrame operations only.

Metadata are quantised to a grid by their rank: a value's place is the share of rows with smaller
values, in 2^bits steps, so places follow the order of the values and are about equally full.  The
cells are visited in the order of the curve and the order is cut into runs of equal counts, so a
shard covers a compact part of every dimension, and files can be skipped by their smallest and
largest value of any of them.  Only the places' first values come to the driver (2^bits of each
dimension).  Cells are at most 2^(bits * dims) (4096 here), which bounds the table that is broadcast
and the one window over all cells.  Rows find their rank inside a cell by parts of about ``part``
rows each, so a cell that holds a third of all rows is ranked by as many tasks as it needs; repeated
rows are spread over the parts by a second hash of their place in the scan.

Defined results: null metadata have grid place 0; null text has size 8; equal rows are placed each;
a text of any length is one row; further columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.llm.common import materialise, table

PART = 256


def hilbert_index(coords: list[Column], bits: int) -> Column:
    """Index of a grid point on the Hilbert curve, by the transposed form with Gray decoding."""
    n = len(coords)
    steps = F.array(*(F.struct(F.lit(1 << b).alias("q"), F.lit(i).alias("i")) for b in range(bits - 1, 0, -1) for i in range(n)))

    def turn(x: Column, s: Column) -> Column:
        q, mine = s["q"], F.element_at(x, s["i"] + 1)
        low = q - 1
        first = F.element_at(x, 1)
        swap = first.bitwiseXOR(mine).bitwiseAND(low)
        flip = mine.bitwiseAND(q) != 0

        def place(v: Column, k: Column) -> Column:
            return (
                F.when(flip & (k == 0), v.bitwiseXOR(low))
                .when(flip, v)
                .when((k == 0) & (s["i"] == 0), v)
                .when((k == 0) | (k == s["i"]), v.bitwiseXOR(swap))
                .otherwise(v)
            )

        return F.transform(x, place)

    x = F.aggregate(steps, F.array(*(c.cast("int") for c in coords)), turn)
    # Gray code: each coordinate takes the ones before it, then all take the carry of the last
    gray = F.transform(x, lambda v, k: F.aggregate(F.slice(x, 1, k + 1), F.lit(0), lambda a, b: a.bitwiseXOR(b)))
    last = F.element_at(gray, -1)
    carry = F.aggregate(F.array(*(F.lit(1 << b) for b in range(bits - 1, 0, -1))), F.lit(0), lambda t, q: F.when(last.bitwiseAND(q) != 0, t.bitwiseXOR(q - 1)).otherwise(t))
    out = F.lit(0).cast("long")
    for b in range(bits - 1, -1, -1):
        for i in range(n):
            bit = F.shiftright(F.element_at(gray, i + 1).bitwiseXOR(carry), b).bitwiseAND(F.lit(1))
            out = F.shiftleft(out, 1).bitwiseOR(bit.cast("long"))
    return out


def grid_cell(dims: list[Column], bits: int) -> Column:
    out = F.lit(0)
    for d in dims:
        out = out * (1 << bits) + F.coalesce(d, F.lit(0)).cast("int")
    return out.cast("int")


def first_values(docs: DataFrame, value: Column, bits: int) -> list[tuple[int, object]]:
    """(place, its smallest value), largest first, without place 0; a place holds about equal counts, or one value.

    Values are ranked by range partitions and sums over these, so many different ones need no
    single task; at most 2^bits come to the driver.
    """
    values = docs.select(value.alias("v")).where("v is not null").groupBy("v").agg(F.count("*").alias("n"))
    values = materialise(values.repartitionByRange("v").select("v", "n", F.spark_partition_id().alias("part")), "shard-values")
    parts = values.groupBy("part").agg(F.sum("n").alias("all"), F.min("v").alias("low"))
    before = Window.orderBy("low").rowsBetween(Window.unboundedPreceding, -1)  # one row per partition
    parts = parts.select("part", F.coalesce(F.sum("all").over(before), F.lit(0)).alias("shift"), F.sum("all").over(Window.partitionBy()).alias("total"))
    inside = Window.partitionBy("part").orderBy("v").rowsBetween(Window.unboundedPreceding, -1)
    ranked = values.withColumn("less", F.coalesce(F.sum("n").over(inside), F.lit(0))).join(F.broadcast(parts), "part")
    place = F.expr(f"(shift + less) * {1 << bits} div total")
    low = ranked.groupBy(place.cast("int").alias("place")).agg(F.min("v").alias("v")).where("place > 0").orderBy(F.desc("v")).collect()
    return [(r.place, r.v) for r in low]


def place_of(value: Column, first: list[tuple[int, object]]) -> Column:
    """Grid place of a value: the last place that begins at or below it."""
    out = F.when(value.isNull(), 0)
    for place, low in first:
        out = out.when(value >= F.lit(low), place)
    return out.otherwise(0)


def document_values() -> list[Column]:
    """Language, source and size (its logarithm in 64ths) of a document."""
    return [F.col("lang").cast("string"), F.col("source").cast("string"), F.floor(F.log2(F.octet_length("text") + F.lit(1.0)) * 64).cast("int")]


def document_dims(docs: DataFrame, bits: int) -> list[Column]:
    return [place_of(v, first_values(docs, v, bits)) for v in document_values()]


def hilbert_shards(docs: DataFrame, shards: int, dims: list[Column] | None = None, bits: int = 4, part: int = PART) -> DataFrame:
    """doc_id, size, text_crc32, curve, shard and slot of every row; shard counts differ by one at most."""
    dims = dims or document_dims(docs, bits)
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
        grid_cell(dims, bits).alias("cell"),
        F.monotonically_increasing_id().alias("scan"),
    )
    rows = materialise(rows, "shard-rows")
    mask, n = (1 << bits) - 1, len(dims)
    coords = [F.shiftright("cell", bits * (n - 1 - i)).bitwiseAND(F.lit(mask)) for i in range(n)]
    cells = rows.groupBy("cell").agg(F.count("*").alias("n")).withColumn("curve", hilbert_index(coords, bits))
    along = Window.orderBy("curve").rowsBetween(Window.unboundedPreceding, -1)
    cells = materialise(cells.withColumn("before", F.coalesce(F.sum("n").over(along), F.lit(0))), "shard-cells")
    total = cells.agg(F.sum("n")).first()[0] or 0
    parts = F.ceil(F.col("n") / F.lit(part))
    placed = rows.join(F.broadcast(cells), "cell")  # at most 2^(bits * dims) rows
    placed = placed.withColumn("part", F.pmod(F.xxhash64("scan"), parts))
    counts = materialise(placed.groupBy("cell", "part").agg(F.count("*").alias("c")), "shard-parts")
    earlier = Window.partitionBy("cell").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select("cell", "part", F.coalesce(F.sum("c").over(earlier), F.lit(0)).alias("shift"))
    inside = Window.partitionBy("cell", "part").orderBy("scan")
    ranked = placed.withColumn("rank", F.row_number().over(inside) - 1).join(counts, ["cell", "part"])
    ranked = ranked.withColumn("rank", F.col("rank") + F.col("before") + F.col("shift"))
    ranked = ranked.withColumn("shard", F.expr(f"rank * {shards} div {max(total, 1)}").cast("int"))
    first = F.expr(f"(cast(shard as bigint) * {total} + {shards - 1}) div {shards}")
    return ranked.select("doc_id", "size", "text_crc32", "curve", "shard", (F.col("rank") - first).alias("slot"))


def write_shards(docs: DataFrame, placed: DataFrame, path: str) -> None:
    """Writes the documents as one folder per shard, in slot order (unique document ids needed)."""
    full = docs.join(placed.select("doc_id", "shard", "slot"), "doc_id")
    full.repartition("shard").sortWithinPartitions("shard", "slot").drop("slot").write.partitionBy("shard").parquet(path)


def shard_statistics(docs: DataFrame, placed: DataFrame) -> DataFrame:
    """Smallest and largest metadata per shard: what a reader needs to skip files."""
    both = docs.select("doc_id", "lang", "source").join(placed, "doc_id")
    cols = [f(c).alias(f"{f.__name__}_{c}") for c in ("lang", "source", "size", "curve") for f in (F.min, F.max)]
    return both.groupBy("shard").agg(F.count("*").alias("rows"), F.sum("size").alias("bytes"), *cols)


def op5_hilbert_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 24 shards under the law of equal counts."""
    placed = hilbert_shards(table(spark, sf_dir, "documents"), 24)
    return placed.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve"
    )
