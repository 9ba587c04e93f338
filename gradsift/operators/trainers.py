"""Distributed trainers as loops of plans: each step commits a new version of state and model.

State is state(worker, coord, u, v): velocity and residual of logical workers; a model is
(coord, w).  What the server does is one small aggregation (the merge), one selection, and one
broadcast of at most P * k ids for exact values.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradsift.operators import recover as R
from gradsift.operators import sketch as S
from gradsift.operators.hashing import HashFamily
from gradsift.plans import cost
from gradsift.plans.durable import Versions, commit, small


def initial_weights(spark, d: int, seed: int = 0, scale: float = 0.0) -> DataFrame:
    """The same model on all workers: seeded by coordinate."""
    u = (R.shuffle_key(F.col("id"), seed) % 2001 - 1000) / 1000.0
    return spark.range(d).select(F.col("id").alias("coord"), (u * scale).alias("w"))


def shard(examples: DataFrame, workers: int, by: str = "example") -> DataFrame:
    """Deals examples to logical workers: evenly by ``example``, or skewed by ``key`` (a column key, whose values stay together)."""
    if by not in ("example", "key"):
        raise ValueError("by is 'example' or 'key'")
    at = F.pmod(F.col("key"), F.lit(workers)) if by == "key" else F.pmod(F.xxhash64("ex_id"), F.lit(workers))
    return examples.withColumn("worker", at.cast("int"))


def apply_update(w: DataFrame, update: DataFrame, eta: float, count: int) -> DataFrame:
    """w - eta * update; the update is sparse and broadcast within the limit."""
    u = small(update.select("coord", F.col("exact").alias("_e")), count)
    return w.join(u, "coord", "left").select("coord", (F.col("w") - eta * F.coalesce("_e", F.lit(0.0))).alias("w"))


@dataclass
class Run:
    """A training run: the model, the workers' state, and metrics(t, name, value) rows."""

    w: DataFrame
    state: DataFrame | None = None
    metrics: list[tuple[int, str, float]] = field(default_factory=list)


# annealed trainer -------------------------------------------------------------


def corrected(g: DataFrame, a: DataFrame | None, eta: float) -> DataFrame:
    """(worker, coord, delta): eta * gradient plus residual; either side may lack a coordinate."""
    if a is None:
        return g.select("worker", "coord", (F.col("g") * eta).alias("delta"))
    both = g.join(a, ["worker", "coord"], "full")
    return both.select("worker", "coord", (F.coalesce("g", F.lit(0.0)) * eta + F.coalesce("a", F.lit(0.0))).alias("delta"))


def subtract_update(v: DataFrame, update: DataFrame, workers: DataFrame) -> DataFrame:
    """Residual of every worker after the common update; also where the worker held nothing."""
    u = update.select("coord", "exact").crossJoin(F.broadcast(workers))
    both = v.join(u, ["worker", "coord"], "full")
    return both.select("worker", "coord", (F.coalesce("delta", F.lit(0.0)) - F.coalesce("exact", F.lit(0.0))).alias("a"))


def train_annealed(
    examples: DataFrame, loss, d: int, k: int, xi: float, steps: int, workers: int, fam: HashFamily, w0: DataFrame | None = None,
    output: str = "weighted", overflow: str = "largest", reduce: str = "mean", seed: int = 0, batch: Callable | None = None, fresh_hash: bool = False,
) -> Run:
    """Step size 1/(t + xi); heavy-or-random recovery of the merged sketch; residuals keep the rest.

    ``weighted`` output averages the iterates with weights (xi + t)^2.  A coordinate changes only
    when picked, so it adds its value times the weights of the steps since its last change.
    """
    spark, kept = examples.sparkSession, Versions()
    count = d if overflow == "keep_all" else k
    start = w0 if w0 is not None else initial_weights(spark, d)
    # acc: the weighted sum of the iterates before the step of the last change, mark: their weights' sum
    w = kept.commit(start.select("coord", "w", F.lit(0.0).alias("acc"), F.lit(0.0).alias("mark")), "w")
    ids = spark.range(workers).select(F.col("id").cast("int").alias("worker"))
    a, total = None, 0.0
    for t in range(1, steps + 1):
        f = HashFamily(fam.rows, fam.cols, fam.seed + t, fam.field) if fresh_hash else fam
        g = loss.gradient(batch(examples, t) if batch else examples, w.select("coord", "w"), d)
        v = kept.commit(corrected(g, a, 1.0 / (t + xi)), "v")
        cells = kept.commit(S.merge(S.sketch(v, f, by=["worker"]), "mean", workers), "cells")
        picks = R.heavy_or_random_picks(cells, f, d, k, seed, t, overflow)
        update = kept.commit(R.exact_refetch(v, picks, count, reduce, workers), "update")
        # iterate t is the one whose gradient was taken at step t
        total += (xi + t) ** 2
        both, hit = w.join(small(update.select("coord", "exact"), count), "coord", "left"), F.col("exact").isNotNull()
        w = both.select(
            "coord", (F.col("w") - F.coalesce("exact", F.lit(0.0))).alias("w"),
            (F.col("acc") + F.when(hit, F.col("w") * (F.lit(total) - F.col("mark"))).otherwise(0.0)).alias("acc"), F.when(hit, F.lit(total)).otherwise(F.col("mark")).alias("mark"),
        )
        w = kept.commit(w, "w")
        a = subtract_update(v, update, ids)
    kept.close("w", "v", "update")
    if output == "weighted":
        return Run(w.select("coord", ((F.col("acc") + F.col("w") * (F.lit(total) - F.col("mark"))) / F.lit(total)).alias("w")), a)
    return Run(w.select("coord", "w"), a)


# momentum trainer and baselines -----------------------------------------------


def advance(state: DataFrame | None, g: DataFrame, m: float, correction: bool = True, accumulate: bool = True) -> DataFrame:
    """(worker, coord, u, v): velocity, and residual that accumulates the velocity (or the gradient)."""
    if state is None:
        both = g.select("worker", "coord", "g", F.lit(0.0).alias("u"), F.lit(0.0).alias("v"))
    else:
        both = g.join(state, ["worker", "coord"], "full").select("worker", "coord", *(F.coalesce(c, F.lit(0.0)).alias(c) for c in ("g", "u", "v")))
    both = both.withColumn("u", F.col("u") * m + F.col("g"))
    step = F.col("u") if correction else F.col("g")
    return both.select("worker", "coord", "u", ((F.col("v") if accumulate else F.lit(0.0)) + step).alias("v"))


def masked(state: DataFrame, update: DataFrame, count: int, mask_velocity: bool = True, residual: str = "zero", share: int = 1, keys=("coord",)) -> DataFrame:
    """State after the update was sent: updated coordinates are zeroed (or the update is subtracted)."""
    sent = small(update.select(*keys, "exact").withColumn("_in", F.lit(True)), count)
    both = state.join(sent, list(keys), "left")
    hit = F.col("_in").isNotNull()
    left = F.lit(0.0) if residual == "zero" else F.col("v") - F.col("exact") / share
    return both.select("worker", "coord", F.when(hit & F.lit(mask_velocity), 0.0).otherwise(F.col("u")).alias("u"), F.when(hit, left).otherwise(F.col("v")).alias("v"))


def clipped(g: DataFrame, limit: float) -> DataFrame:
    """Each worker's gradient scaled down to the norm ``limit`` at most."""
    norm = g.groupBy("worker").agg(F.sqrt(F.sum(F.col("g") * F.col("g"))).alias("_n"))  # one row per worker
    return g.join(F.broadcast(norm), "worker").select("worker", "coord", (F.col("g") * F.least(F.lit(1.0), F.lit(limit) / F.greatest("_n", F.lit(1e-300)))).alias("g"))


def sparsity_warmup(d: int, k: int, steps: int) -> Callable[[int], int]:
    """k of step t: from d down to k in equal ratios over ``steps`` steps."""
    return lambda t: max(k, round(d * (k / d) ** min(1.0, t / max(1, steps))))


def train_momentum(
    examples: DataFrame, loss, d: int, k: int | Callable[[int], int], steps: int, workers: int, eta: float | Callable[[int], float] = 0.1, m: float = 0.9, p: int = 4,
    fam: HashFamily | None = None, method: str = "sketch", w0: DataFrame | None = None, mask_velocity: bool = True, momentum_correction: bool = True,
    residual: str = "zero", accumulate: bool = True, reduce: str = "sum", refetch: bool = True, groups: DataFrame | None = None, cell_bits: int = 32,
    seed: int = 0, batch: Callable | None = None, evaluate: DataFrame | None = None, clip: float | None = None,
) -> Run:
    """Momentum trainer; ``method`` chooses what is sent.

    ``sketch``: top p * k of the merged sketch, refetched, best k.  ``true_top_k``: k largest of the
    exact sum.  ``local_top_k``: each worker's own k largest.  ``random_candidates``: p * k random
    coordinates, best k.  ``dense``: everything (momentum SGD; nothing is masked).  Coordinates of
    ``groups`` that are marked as not compressed are sent in full by every method.  ``k`` may be a
    function of the step (``sparsity_warmup``), ``clip`` bounds the norm of each worker's gradient.

    A step writes the advanced state, the update and the model once each; what the update zeroes is
    applied when the next step reads the state.  The last two versions of each table are kept.
    """
    spark, kept, every = examples.sparkSession, Versions(), k
    run = Run(kept.commit(w0 if w0 is not None else initial_weights(spark, d), "w"))
    velocity = None
    for t in range(1, steps + 1):
        rate, k = eta(t) if callable(eta) else eta, every(t) if callable(every) else every
        g = loss.gradient(batch(examples, t) if batch else examples, run.w, d)
        g = g if clip is None else clipped(g, clip)
        state = kept.commit(advance(run.state, g, m, momentum_correction, accumulate), "state")
        v = state.select("worker", "coord", F.col("v").alias("delta"))
        full = None
        if groups is not None:
            v, open_ = R.split_groups(v, groups)
            full = open_.groupBy("coord").agg(F.sum("delta").alias("exact"))
        keys, count = ("coord",), k
        if method == "dense":
            update, count = v.groupBy("coord").agg(F.sum("delta").alias("exact")), d
        elif method == "true_top_k":
            update = R.true_top_k(v, k).withColumnRenamed("value", "exact")
        elif method == "random_candidates":
            update = R.recover_random_candidates(d, k, p, v, seed, t)
        elif method == "local_top_k":
            sent = kept.commit(R.local_top_k(v, k).withColumnRenamed("value", "exact"), "sent")
            update, keys, count = sent.groupBy("coord").agg(F.sum("exact").alias("exact")), ("worker", "coord"), k * workers
        elif method == "sketch":
            cells = S.merge(S.sketch(v, fam, by=["worker"]), "mean", workers)
            if cell_bits == 16:
                cells = S.dequantise(S.quantise(cells))
            update = R.recover_over_ask(kept.commit(cells, "cells"), fam, d, k, p, v, refetch=refetch)
            if not refetch:  # estimates are of the mean
                update = update.withColumn("exact", F.col("exact") * workers)
        else:
            raise ValueError(f"no method {method}")
        if full is not None:
            update = update.select("coord", "exact").unionByName(full)
            count = d
        update = kept.commit(update.select("coord", "exact"), "update")
        sent = sent if method == "local_top_k" else update
        if method == "local_top_k" and full is not None:
            sent = sent.select("worker", "coord", "exact").unionByName(state.select("worker", "coord").join(full, "coord"))
        run.state = masked(state, sent, count, mask_velocity and method != "dense", residual, workers if keys == ("coord",) else 1, keys)
        step = update
        if reduce == "mean":
            step = step.withColumn("exact", F.col("exact") / workers)
        if not momentum_correction:  # momentum on the server, on what was recovered
            step = step if velocity is None else step.join(velocity, "coord", "full").select("coord", (F.coalesce("exact", F.lit(0.0)) + m * F.coalesce("vel", F.lit(0.0))).alias("exact"))
            step = kept.commit(step.select("coord", "exact"), "vel")
            velocity, count = step.withColumnRenamed("exact", "vel"), d
        run.w = kept.commit(apply_update(run.w, step, rate, count), "w")
        union = update.count()
        sent_numbers = {
            "dense": cost.comm_dense(d), "true_top_k": cost.comm_true_top_k(d, k), "local_top_k": cost.comm_local(k, union),
            "random_candidates": p * k + k, "sketch": cost.comm_sketch(fam.rows, fam.cols, p if refetch else 0, k, cell_bits) if fam else 0,
        }[method]
        run.metrics += [(t, "updated", float(union)), (t, "numbers", float(sent_numbers))]
        if evaluate is not None:
            run.metrics.append((t, "loss", float(loss.evaluate(evaluate, run.w, d).first()[0])))
    kept.close("w", "state", "update", "sent")
    return run


def train_dense(examples, loss, d, steps, workers, eta=0.1, m=0.0, **more) -> Run:
    """Uncompressed SGD; with workers=1 plain SGD on one machine."""
    return train_momentum(examples, loss, d, d, steps, workers, eta, m, method="dense", **more)


def train_true_top_k(examples, loss, d, k, steps, workers, eta=0.1, m=0.9, **more) -> Run:
    return train_momentum(examples, loss, d, k, steps, workers, eta, m, method="true_top_k", **more)


def train_local_top_k(examples, loss, d, k, steps, workers, eta=0.1, m=0.9, **more) -> Run:
    return train_momentum(examples, loss, d, k, steps, workers, eta, m, method="local_top_k", **more)


def train_random_candidates(examples, loss, d, k, p, steps, workers, eta=0.1, m=0.9, **more) -> Run:
    return train_momentum(examples, loss, d, k, steps, workers, eta, m, p, method="random_candidates", **more)
