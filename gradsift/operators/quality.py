"""Accuracy measures: classification, corpus BLEU, recall, excess risk."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def accuracy(pred: DataFrame, truth: str = "y", guess: str = "pred") -> DataFrame:
    return pred.agg(F.avg(F.when(F.col(truth) == F.col(guess), 1.0).otherwise(0.0)).alias("accuracy"))


def bleu_pieces(pairs: DataFrame, max_n: int = 4) -> DataFrame:
    """n, matched, total of pairs(pair_id, candidate, reference) of token arrays; counts are clipped, inside the row of the pair."""

    def run(batches):
        total, matched = Counter(), Counter()
        for b in batches:
            for c, r in zip(b.column("candidate").to_pylist(), b.column("reference").to_pylist(), strict=True):
                for n in range(1, max_n + 1):
                    have, want = (Counter(" ".join(s[i : i + n]) for i in range(len(s or []) - n + 1)) for s in (c, r))
                    total[n] += have.total()
                    matched[n] += (have & want).total()
        rows = [(n, matched[n], x) for n, x in sorted(total.items()) if x]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int32(), pa.int64(), pa.int64()))], ["n", "matched", "total"])

    pieces = pairs.select("candidate", "reference").mapInArrow(run, "n int, matched long, total long")
    return pieces.groupBy("n").agg(F.sum("matched").alias("matched"), F.sum("total").alias("total"))


def corpus_bleu(pairs: DataFrame, max_n: int = 4) -> DataFrame:
    """n, matched, total, brevity, score (0 to 100; the same score on each row)."""
    lengths = pairs.agg(F.sum(F.size("candidate")).alias("c"), F.sum(F.size("reference")).alias("r"))
    pieces = bleu_pieces(pairs, max_n).crossJoin(F.broadcast(lengths))
    brevity = F.when(F.col("c") >= F.col("r"), 1.0).otherwise(F.exp(1 - F.col("r") / F.col("c")))
    log = F.when(F.col("matched") > 0, F.log(F.col("matched") / F.col("total")))
    all_ = Window.partitionBy(F.lit(1))  # max_n rows
    score = F.when(F.count(log).over(all_) == max_n, F.exp(F.sum(log).over(all_) / max_n) * brevity * 100).otherwise(0.0)
    return pieces.select("n", "matched", "total", F.round(brevity, 6).alias("brevity"), F.round(score, 6).alias("score"))


def recall_at_k(found: DataFrame, truth: DataFrame, k: int) -> float:
    return found.select("coord").join(truth.select("coord"), "coord", "left_semi").count() / k


def closed_form_ridge(examples: DataFrame, d: int, l2: float) -> np.ndarray:
    """Minimiser of the mean ridge loss from its normal equations, d small."""
    x = examples.select("ex_id", "y", F.inline("x"))
    a = x.select("ex_id", F.col("coord").alias("i"), F.col("val").alias("a"))
    pairs = x.join(a, "ex_id").groupBy("i", "coord").agg(F.sum(F.col("a") * F.col("val")).alias("s"))
    right = x.groupBy("coord").agg(F.sum(F.col("y") * F.col("val")).alias("s"))
    n = examples.count()
    m, b = np.eye(d) * l2, np.zeros(d)
    for r in pairs.collect():  # d * d rows
        m[r.i, r.coord] += r.s / n
    for r in right.collect():
        b[r.coord] = r.s / n
    return np.linalg.solve(m, b)


def curvature(examples: DataFrame, d: int, l2: float) -> tuple[float, float]:
    """(smoothness, strong convexity) of the mean ridge loss: extreme eigenvalues of its Hessian."""
    x = examples.select("ex_id", F.inline("x"))
    a = x.select("ex_id", F.col("coord").alias("i"), F.col("val").alias("a"))
    m, n = np.eye(d) * l2, examples.count()
    for r in x.join(a, "ex_id").groupBy("i", "coord").agg(F.sum(F.col("a") * F.col("val")).alias("s")).collect():
        m[r.i, r.coord] += r.s / n
    e = np.linalg.eigvalsh(m)
    return float(e[-1]), float(e[0])


def iters_to(metrics: list[tuple[int, str, float]], target: float, name: str = "loss") -> int | None:
    """First step at which a measure falls to the target, or None."""
    return next((t for t, n, v in sorted(metrics) if n == name and v <= target), None)
