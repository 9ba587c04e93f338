import numpy as np
import pytest
from pyspark.sql import functions as F

from gradsift.functions import udfs
from gradsift.operators import recover as R
from gradsift.operators import sketch as S
from gradsift.operators.hashing import HashFamily
from gradsift.plans import bounds, cost, topology


def vector(spark, values, workers=1):
    return spark.createDataFrame([(i % workers, i, v) for i, v in enumerate(values)], "worker int, coord long, delta long")


def test_hash_family_is_even_and_matches_numpy(spark):
    fam = HashFamily(5, 64, 1)
    x = np.arange(20_000)
    bucket, sign = fam.numpy(x)
    for b, s in zip(bucket, sign, strict=True):
        n = np.bincount(b, minlength=64)
        assert len(n) == 64 and ((n - n.mean()) ** 2 / n.mean()).sum() / 63 < 2 and abs(s.mean()) < 0.05
    got = spark.range(300).select(F.col("id"), F.inline(fam.cells_of(F.col("id")))).collect()
    assert all(bucket[r.row, r.id] == r.bucket and sign[r.row, r.id] == r.sign for r in got)
    with pytest.raises(Exception):
        S.validate_deltas(vector(spark, [1]).withColumn("coord", F.lit(-1).cast("long")), fam.field).collect()


def test_linearity_is_exact_for_integers(spark):
    fam, rnd = HashFamily(3, 16, 5), np.random.default_rng(1)
    v = vector(spark, rnd.integers(-1000, 1000, 200).tolist(), 4)
    one = {(r.row, r.bucket): r.cell for r in S.sketch(v, fam).collect()}
    merged = {(r.row, r.bucket): r.cell for r in S.merge(S.sketch(v.repartition(7), fam, by=["worker"])).collect()}
    assert one == merged
    rest = S.subtract(S.sketch(v, fam), S.sketch(v.where("worker < 2"), fam))
    assert {(r.row, r.bucket): r.cell for r in rest.collect() if r.cell} == {(r.row, r.bucket): r.cell for r in S.sketch(v.where("worker >= 2"), fam).collect() if r.cell}


def test_estimate_bounds_over_seeds():
    """Point queries and norms hold for nearly all of 20 hash draws."""
    rnd = np.random.default_rng(2)
    v = rnd.normal(size=2000)
    v[::100] *= 40
    good = norms = heavies = 0
    for seed in range(20):
        fam = HashFamily(5, 256, seed)
        bucket, sign = fam.numpy(np.arange(len(v)))
        table = np.array([np.bincount(b, weights=s * v, minlength=256) for b, s in zip(bucket, sign, strict=True)])
        est = np.median(sign * np.take_along_axis(table, bucket, 1), axis=0)
        norm = np.median((table**2).sum(1))
        good += np.mean(np.abs(est - v) <= 3 * np.linalg.norm(v) / 16) > 0.99
        norms += 0.5 <= norm / (v @ v) <= 1.5
        heavy = np.flatnonzero(v**2 > (v @ v) / 20)
        heavies += set(heavy) <= set(np.flatnonzero(est**2 > norm / 64))
    assert good >= 19 and norms >= 19 and heavies >= 19


@pytest.mark.parametrize("values,k,heavy", [([100, -90, 1, 1, 0, 0, 1, 1], 3, 2), ([10, -10, 0, 0, 0, 0, 0, 0], 2, 2), ([10, -10, 10, -10, 0, 0, 0, 0], 2, 0), ([1] * 8, 4, 0), ([0] * 8, 3, None)])
def test_heavy_or_random_cases(spark, values, k, heavy):
    fam = HashFamily(7, 512, 3)
    v = vector(spark, values)
    got = R.recover_heavy_or_random(S.sketch(v, fam), fam, len(values), k, v, seed=1).collect()
    if heavy is None:
        assert got == []  # a zero vector recovers nothing
        return
    assert len(got) == k and all(r.exact == values[r.coord] for r in got)
    assert sum(r.is_heavy for r in got) == heavy


def test_overflow_rules_and_full_k(spark):
    fam, values = HashFamily(7, 512, 3), [50, 49, -48, 47, 0, 0, 0, 0]
    v = vector(spark, values)
    cells = S.sketch(v, fam)
    est = {r.coord for r in R.heavy_or_random_picks(cells, fam, 8, 8, 0).collect()}
    assert est == set(range(8))
    keep = R.heavy_or_random_picks(cells, fam, 8, 4, 0, overflow="keep_all").collect()
    assert {r.coord for r in keep if r.is_heavy} <= {0, 1, 2, 3} and len(keep) >= 4


def test_random_fill_is_uniform(spark):
    counts = np.zeros(40)
    ids = spark.range(40).withColumnRenamed("id", "coord").cache()
    for t in range(60):
        for r in ids.orderBy(R.shuffle_key(F.col("coord"), 5, t), "coord").limit(10).collect():
            counts[r.coord] += 1
    assert counts.sum() == 600 and counts.max() < 30 and counts.min() > 3


def test_contraction_over_seeds():
    rnd = np.random.default_rng(0)
    x = rnd.normal(size=100) * np.linspace(0.1, 3, 100)
    top = np.argsort(-np.abs(x))[:10]
    ratio = lambda keep: 1 - (x[keep] ** 2).sum() / (x @ x)
    assert ratio(top) <= bounds.contraction_bound(100, 10)
    assert np.mean([ratio(rnd.permutation(100)[:10]) for _ in range(400)]) == pytest.approx(0.9, abs=0.02)


def test_quantised_cells(spark):
    cells = spark.createDataFrame([(0, i, float(v)) for i, v in enumerate([1000.0, -3.25, 0.5, 0.0])], "row int, bucket int, cell double")
    for mode, tol in (("scaled", 0.02), ("stochastic", 0.04), ("half", 0.5)):
        got = {r.bucket: r.cell for r in S.dequantise(S.quantise(cells, mode=mode)).collect()}
        assert all(abs(got[r.bucket] - r.cell) <= tol for r in cells.collect())


def test_numpy_kernels_agree(spark):
    fam = HashFamily(3, 32, 9)
    v = vector(spark, list(range(-40, 40)), 2)
    rows = lambda df: {tuple(r) for r in df.select("row", "bucket", "cell").collect()}
    assert rows(S.sketch(v, fam)) == rows(S.sketch_blocks(v, fam))
    a, b = (sorted(map(tuple, S.estimate_all(S.sketch(v, fam), fam, 80, kernel=k).collect())) for k in ("sql", "numpy"))
    assert a == b
    udfs.register_all(spark, fam)
    assert spark.sql("SELECT * FROM sketch_rows(7, 2.0D)").count() == 3


def test_costs_reproduce_the_stated_factors():
    assert cost.compression(90_000_000, 5, 1_000_000, 36, 100_000) == pytest.approx(20.7, abs=0.1)
    assert cost.compression(90_000_000, 15, 180_000, 16, 100_000) == pytest.approx(40.9, abs=0.1)
    assert cost.compression(73_000_000, 5, 180_000, 26, 100_000) == pytest.approx(40.6, abs=0.1)
    assert round(cost.effective_compression(17, 1.5)) == 11
    assert 2 * 6_500_000 / cost.comm_local(100_000, cost.local_union_cap(100_000, 256, 6_500_000)) == pytest.approx(2, abs=0.05)
    with pytest.raises(ValueError):
        bounds.min_offset(10, 1, beta=4)


def test_spanning_trees():
    assert len(topology.spanning_tree(topology.ring(9), 9)) == 8 == len(topology.spanning_tree(topology.complete(9), 9))
    with pytest.raises(ValueError):
        topology.spanning_tree([(0, 1)], 3)
