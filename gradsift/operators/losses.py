"""Losses on sparse examples(ex_id, worker, y, x array<struct<coord, val>>) as relational plans.

A gradient frame is (worker, coord, g): the mean over a worker's examples plus the penalty.  The
weights join the exploded features (broadcast within the limit, else by merge), one aggregation
brings an example's features together again, and one gives the gradient per worker; its partial
sums run before the exchange.  ``ex_id`` must be unique: rows that share one are one example.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gradsift.operators.simulate import Mlp
from gradsift.plans.durable import small


class LinearLoss:
    """Loss of a score z = <x, w>; subclasses give its slope and value in z."""

    def __init__(self, l2: float = 0.0):
        self.l2 = l2

    def slope(self, z: Column, y: Column) -> Column:
        raise NotImplementedError

    def value(self, z: Column, y: Column) -> Column:
        raise NotImplementedError

    def scores(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        long = examples.select("ex_id", "worker", "y", F.inline("x"))
        joined = long.join(small(w.select("coord", "w"), count), "coord", "left")
        return joined.groupBy("ex_id", "worker", "y").agg(
            F.sum(F.col("val") * F.coalesce("w", F.lit(0.0))).alias("z"), F.collect_list(F.struct("coord", "val")).alias("x")
        )

    def gradient(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        n = examples.groupBy("worker").agg(F.count("*").alias("n"))
        s = self.scores(examples, w, count).select("worker", self.slope(F.col("z"), F.col("y")).alias("s"), F.inline("x"))
        g = s.groupBy("worker", "coord").agg(F.sum(F.col("s") * F.col("val")).alias("g")).join(F.broadcast(n), "worker")
        g = g.select("worker", "coord", (F.col("g") / F.col("n")).alias("g"))
        if self.l2:
            decay = w.crossJoin(F.broadcast(n.select("worker"))).select("worker", "coord", (F.col("w") * self.l2).alias("g"))
            g = g.unionByName(decay).groupBy("worker", "coord").agg(F.sum("g").alias("g"))
        return g

    def evaluate(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        """One row: mean loss without penalty."""
        return self.scores(examples, w, count).agg(F.avg(self.value(F.col("z"), F.col("y"))).alias("loss"))


class RidgeLoss(LinearLoss):
    def slope(self, z, y):
        return z - y

    def value(self, z, y):
        return (z - y) * (z - y) / 2


class LogisticLoss(LinearLoss):
    """y in {0, 1}."""

    def slope(self, z, y):
        return 1 / (1 + F.exp(-z)) - y

    def value(self, z, y):
        s = F.when(y > 0, -z).otherwise(z)
        return F.greatest(s, F.lit(0.0)) + F.log1p(F.exp(-F.abs(s)))


class HingeLoss(LinearLoss):
    """y in {0, 1}; a subgradient at the kink is 0."""

    def slope(self, z, y):
        sign = 2 * y - 1
        return F.when(sign * z < 1, -sign).otherwise(F.lit(0.0))

    def value(self, z, y):
        return F.greatest(1 - (2 * y - 1) * z, F.lit(0.0))


class AbsLoss(LinearLoss):
    def slope(self, z, y):
        return F.signum(z - y)

    def value(self, z, y):
        return F.abs(z - y)


class SoftmaxLoss:
    """Multinomial logistic; the coordinate of feature f and class c is f * classes + c."""

    def __init__(self, classes: int, l2: float = 0.0):
        self.classes, self.l2 = classes, l2

    def _errors(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        long = examples.select("ex_id", "worker", "y", F.inline("x"))
        long = long.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(self.classes - 1)))).withColumn("coord", F.col("coord") * self.classes + F.col("c"))
        z = long.join(small(w.select("coord", "w"), count), "coord", "left")
        z = z.groupBy("ex_id", "worker", "y", "c").agg(F.sum(F.col("val") * F.coalesce("w", F.lit(0.0))).alias("z"), F.collect_list(F.struct("coord", "val")).alias("x"))
        ex = Window.partitionBy("ex_id")
        z = z.withColumn("m", F.max("z").over(ex)).withColumn("s", F.sum(F.exp(F.col("z") - F.col("m"))).over(ex))
        return z.withColumn("p", F.exp(F.col("z") - F.col("m")) / F.col("s"))

    def gradient(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        n = examples.groupBy("worker").agg(F.count("*").alias("n"))
        e = self._errors(examples, w, count)
        err = F.col("p") - F.when(F.col("c") == F.col("y"), 1.0).otherwise(0.0)
        g = e.select("worker", err.alias("e"), F.inline("x")).groupBy("worker", "coord").agg(F.sum(F.col("e") * F.col("val")).alias("g"))
        g = g.join(F.broadcast(n), "worker").select("worker", "coord", (F.col("g") / F.col("n")).alias("g"))
        if self.l2:
            decay = w.crossJoin(F.broadcast(n.select("worker"))).select("worker", "coord", (F.col("w") * self.l2).alias("g"))
            g = g.unionByName(decay).groupBy("worker", "coord").agg(F.sum("g").alias("g"))
        return g

    def predict(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        """(ex_id, y, pred): the class of the largest score, the smallest class among equals."""
        return self._errors(examples, w, count).groupBy("ex_id", "y").agg(F.max_by("c", F.struct("p", -F.col("c"))).alias("pred"))

    def evaluate(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        e = self._errors(examples, w, count).where("c = y")
        return e.agg(F.avg(-F.log(F.greatest("p", F.lit(1e-300)))).alias("loss"))


class MlpLoss:
    """Softmax over one hidden layer; the model is the vector of ``simulate.Mlp``, coordinate by coordinate.

    Every task keeps dense sums of its workers' gradients over the Arrow batches it reads and emits
    each worker's vector once, so what is shuffled is tasks * workers * d rows at most.  The model goes
    to the tasks as one vector, whose size is checked.
    """

    #: Parameters that a task may hold per worker.
    MOST = 8_000_000

    def __init__(self, features: int, hidden: int, classes: int, act: str = "tanh"):
        self.net = Mlp(features, hidden, classes, act)
        self.d = self.net.d
        if self.d > self.MOST:
            raise ValueError(f"model of {self.d} parameters, at most {self.MOST} fit a task")

    def _weights(self, w: DataFrame) -> np.ndarray:
        rows = w.where((F.col("coord") >= 0) & (F.col("coord") < self.d)).select("coord", "w").toArrow()  # d rows at most
        out = np.zeros(self.d)
        out[rows.column("coord").to_numpy()] = rows.column("w").to_numpy()
        return out

    def _blocks(self, batch: pa.RecordBatch):
        """(worker, features, classes) of bounded dense blocks of examples."""
        lists = batch.column("x")
        size = lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
        flat = lists.flatten()
        coord, val = flat.field("coord").to_numpy(zero_copy_only=False), flat.field("val").to_numpy(zero_copy_only=False)
        worker, y = batch.column("worker").to_numpy(zero_copy_only=False), batch.column("y").to_numpy(zero_copy_only=False).astype(int)
        end = np.cumsum(size)
        step = max(1, 4_000_000 // self.net.shape[0])
        for i in range(0, len(size), step):
            j = min(len(size), i + step)
            lo, hi = (end[i - 1] if i else 0), end[j - 1]
            x = np.zeros((j - i, self.net.shape[0]))
            np.add.at(x, (np.repeat(np.arange(j - i), size[i:j]), coord[lo:hi]), val[lo:hi])
            for k in np.unique(worker[i:j]):
                own = worker[i:j] == k
                yield int(k), x[own], y[i:j][own]

    def gradient(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        at = self._weights(w)

        def run(batches):
            sums: dict[int, np.ndarray] = {}
            n: dict[int, int] = {}
            for batch in batches:
                for k, x, y in self._blocks(batch):
                    sums[k] = sums.get(k, 0.0) + self.net.gradient(at, x, y) * len(y)
                    n[k] = n.get(k, 0) + len(y)
            for k, g in sums.items():
                yield pa.RecordBatch.from_arrays([pa.array(np.full(self.d, k, np.int32)), pa.array(np.arange(self.d)), pa.array(g), pa.array(np.full(self.d, n[k]))], ["worker", "coord", "g", "n"])

        parts = examples.select("worker", "y", "x").mapInArrow(run, "worker int, coord long, g double, n long")
        return parts.groupBy("worker", "coord").agg((F.sum("g") / F.sum("n")).alias("g"))

    def _measured(self, examples: DataFrame, w: DataFrame) -> DataFrame:
        at = self._weights(w)

        def run(batches):
            for batch in batches:
                for _, x, y in self._blocks(batch):
                    loss, right = self.net.evaluate(at, x, y)
                    yield pa.RecordBatch.from_arrays([pa.array([loss * len(y)]), pa.array([right * len(y)]), pa.array([len(y)])], ["loss", "correct", "n"])

        return examples.select("worker", "y", "x").mapInArrow(run, "loss double, correct double, n long")

    def evaluate(self, examples: DataFrame, w: DataFrame, count: int) -> DataFrame:
        """One row: mean loss, and the share of examples whose class scores highest."""
        return self._measured(examples, w).agg((F.sum("loss") / F.sum("n")).alias("loss"), (F.sum("correct") / F.sum("n")).alias("accuracy"))

    def start(self, spark, seed: int = 0) -> DataFrame:
        """(coord, w): the seeded first model."""
        return spark.createDataFrame(pa.table({"coord": np.arange(self.d), "w": self.net.start(seed)}))


def grad_moments(g: DataFrame) -> DataFrame:
    """W, g2, var: mean squared norm of the workers' gradients and their variance around the mean."""
    per = g.groupBy("worker").agg(F.sum(F.col("g") * F.col("g")).alias("n2")).agg(F.avg("n2").alias("g2"), F.count("*").alias("W"))
    mean = g.groupBy("coord").agg(F.sum("g").alias("s")).crossJoin(F.broadcast(per.select("W")))
    norm = mean.agg(F.sum(F.pow(F.col("s") / F.col("W"), 2)).alias("m2"))
    return per.crossJoin(F.broadcast(norm)).select("W", "g2", (F.col("g2") - F.col("m2")).alias("var"))
