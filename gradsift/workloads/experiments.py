"""The experiment workloads on stand-ins, as sweeps: one row per setting, mean and spread over seeds.

Every method has its own step size from the same small grid, chosen on the training loss of two
seeds that are not reported.  Scores belong to synthetic stand-ins and are not comparable with
published ones; what is compared is the order of methods and how measures move.
"""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from gradsift.operators import recover as R
from gradsift.operators import simulate as SIM
from gradsift.plans.bounds import min_offset
from gradsift.plans.durable import commit
from gradsift.sources.tables import load_table
from gradsift.workloads import fixtures as X
from gradsift.workloads.registry import query
from gradsift.workloads.relational_queries import document_trigrams

SEEDS, ETAS = 5, (0.03, 0.1, 0.3, 1.0)
RESULT = "name string, method string, W int, k int, P int, r int, c int, eta double, seeds int, train_loss double, train_loss_sd double, accuracy double, accuracy_sd double, updated double, numbers double, factor double"


def bounded(rows, width: int):
    """All rows of a training set of ``width`` numbers each, on the driver; refuses, before it collects, what exceeds ``SIM.MAX_VALUES``."""
    n = rows.count()
    if n * width > SIM.MAX_VALUES:
        raise ValueError(f"training set too large for a sweep: {n} rows of {width} numbers, at most {SIM.MAX_VALUES} numbers")
    return rows.toPandas()


def teacher_data(spark, d):
    """Unit vectors labelled by the largest of ten seeded directions; all rows, by id order of a hash."""
    rows = bounded(load_table(spark, d, "embeddings").orderBy(F.xxhash64("vec_id"), "vec_id").select("vec_id", "embedding"), 64)
    x = np.stack(rows["embedding"].to_numpy()).astype(float) * 8
    y = (x @ np.random.default_rng(7).normal(size=(64, 10))).argmax(1)
    return x, y


def language_data(spark, d, features: int = 512):
    """Normalised hashed trigram counts of whole texts and the language, all documents."""
    docs = load_table(spark, d, "documents").select("doc_id", F.coalesce("lang", F.lit("")).alias("lang"))
    docs = bounded(docs.join(document_trigrams(spark, d, features), "doc_id").orderBy(F.xxhash64("doc_id"), "doc_id"), features)
    x = np.zeros((len(docs), features))
    for i, (c, n) in enumerate(zip(docs["coord"], docs["n"], strict=True)):
        x[i, np.asarray(c, np.int64)] = n
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1)
    names = sorted(set(docs["lang"]))
    return x * 4, np.array([names.index(v) for v in docs["lang"]], int)


def language_rows(spark, d, features: int = 512):
    """(place, coord, n, y) of all documents as in ``language_data``, their number and that of the languages; rows stay sparse and distributed."""
    docs = load_table(spark, d, "documents").select("doc_id", F.coalesce("lang", F.lit("")).alias("lang"))
    names = sorted(r.lang for r in docs.select("lang").distinct().collect())  # languages
    docs = docs.join(document_trigrams(spark, d, features), "doc_id")
    y = F.array_position(F.array(*map(F.lit, names)), F.col("lang")).cast("int") - 1
    rows, n = placed(docs.select("doc_id", F.col("coord").cast("array<int>").alias("coord"), F.col("n").cast("array<int>").alias("n"), y.alias("y")), [F.xxhash64("doc_id"), "doc_id"])
    return rows, n, len(names)


def ridge_data(spark, d):
    """Features and target of all orders."""
    rows = bounded(X.order_features(spark, d).orderBy("ex_id"), X.DIM)
    return rows[[f"x{i}" for i in range(X.DIM)]].to_numpy(), rows["y"].to_numpy()


def placed(rows, key: list):
    """(rows with their place in the order of ``key``, number of rows): written sorted, numbered by the sums over tasks."""
    rows = commit(rows.orderBy(*key).withColumns({"task": F.spark_partition_id(), "local": F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))}), "placed")
    before, at = [], 0
    for r in sorted(rows.groupBy("task").count().collect()):  # one row for each task of a sort
        before.append((r.task, at))
        at += r["count"]
    shift = rows.sparkSession.createDataFrame(before, "task int, shift long")
    return rows.join(F.broadcast(shift), "task").withColumn("place", F.col("local") + F.col("shift")).drop("task", "local", "shift"), at


def draws(seed: int, n: int, steps: int, batch: int) -> list[np.ndarray]:
    """Rows of each step, of n; a shorter run draws the first ones."""
    rnd = np.random.default_rng([seed, 17])
    return [rnd.choice(n, batch, replace=False) if batch < n else np.arange(n) for _ in range(steps)]


def by_seed(rows, n: int, seeds, steps: int, batch: int, play, schema: str):
    """Plays all runs of a seed in one task, on the rows that its steps draw of the first n: at most steps * batch, whatever n is.

    ``play(seed, table, draw)``: the rows drawn, sorted by place, and the function that gives the rows of a step in the table.
    """
    some = [np.unique(np.concatenate(draws(s, n, steps, batch))) for s in seeds]
    wanted = pa.table({"seed": pa.array(np.repeat(np.array(seeds, np.int32), [len(x) for x in some])), "place": pa.array(np.concatenate(some), pa.int64())})

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by("place")
        seed, have = t.column("seed")[0].as_py(), t.column("place").to_numpy()
        own = [np.searchsorted(have, x) for x in draws(seed, n, steps, batch)]
        return play(seed, t, lambda step: own[step - 1])

    wanted = F.broadcast(rows.sparkSession.createDataFrame(wanted))  # seeds * steps * batch rows of two numbers
    return rows.join(wanted, "place").groupBy("seed").applyInArrow(run, schema)


CONTEXTS = 1 << 14


def char_places(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(hashed context of the three characters before, code point) of every place of a text."""
    p = np.frombuffer((text or "").encode("utf-32-le"), "<u4").astype(np.int64)
    return (p[:-3] * 961 + p[1:-2] * 31 + p[2:-1]) * 7919 % 2147483647 % CONTEXTS, p[3:]


def char_documents(spark, d):
    """German documents: doc_id, lower-cased text, whether held out."""
    test = R.shuffle_key(F.col("doc_id"), 1) % 10 < 2
    return load_table(spark, d, "documents").where("lang = 'de'").select(F.col("doc_id").cast("long").alias("doc_id"), F.lower("text").alias("t"), test.alias("test"))


def char_data(spark, d, workers: int = 4):
    """Next character from the three before it (hashed): counts (worker, context, letter) over all places of all German texts, and those of held-out documents.

    A letter of the training texts is a class of its own; the last class is kept for letters that only held-out texts have.
    """

    def counted(keys):
        flat, n = np.unique(np.concatenate(keys), return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(flat), pa.array(n)], ["key", "n"])

    def run(batches):
        for b in batches:
            keys, size = [np.zeros(0, np.int64)], 0
            for i, t, test in zip(*(b.column(c).to_pylist() for c in ("doc_id", "t", "test")), strict=True):
                ctx, point = char_places(t)
                keys.append(((int(test) * workers + i % workers) * CONTEXTS + ctx) * 0x110000 + point)
                size += len(ctx)
                if size > 1 << 20:
                    yield counted(keys)
                    keys, size = keys[:1], 0
            yield counted(keys)

    rows = char_documents(spark, d).mapInArrow(run, "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).toPandas()  # contexts x letters, not places
    key, n = rows["key"].to_numpy(np.int64), rows["n"].to_numpy(np.int64)
    point, ctx, worker, held = key % 0x110000, key // 0x110000 % CONTEXTS, key // 0x110000 // CONTEXTS % workers, key // 0x110000 // CONTEXTS // workers
    known = np.unique(point[held == 0])
    letters = max(64, len(known) + 1)
    place = np.searchsorted(known, point)
    y = np.where(np.isin(point, known), place, letters - 1)
    out = []
    for part in (0, 1):
        x = np.zeros((workers, CONTEXTS, letters), np.int64)
        own = held == part
        np.add.at(x, (worker[own], ctx[own], y[own]), n[own])
        out.append((x if part == 0 else x.sum(0, keepdims=True), np.zeros(workers if part == 0 else 1, int)))
    return (*out, known)


def sweep(spark, data, model: dict, settings: list[dict]):
    """Runs every setting on ``SEEDS`` seeds with its best step size; tasks are runs, not rows."""
    x, y = data
    if isinstance(x, tuple):  # split already
        train, test = x, y
    else:
        cut = int(len(y) * 0.8)
        train, test = (x[:cut], y[:cut]), (x[cut:], y[cut:])
    if train[0].size + test[0].size > SIM.MAX_VALUES:
        raise ValueError("training set too large for a sweep")
    kinds = {"softmax": SIM.Softmax, "mlp": SIM.Mlp, "ridge": SIM.Ridge, "context_softmax": SIM.ContextSoftmax, "context_mlp": SIM.ContextMlp}

    def run(frames):
        build = lambda: kinds[model["kind"]](*model["args"])
        for pdf in frames:
            for text in pdf["setting"]:
                s = json.loads(text)
                name, etas, seeds = s.pop("name"), s.pop("etas", ETAS), s.pop("seeds", SEEDS)
                trial = lambda eta, seed, s=s: SIM.simulate(build(), train, test, eta=eta, seed=seed, **s)
                with np.errstate(all="ignore"):
                    scores = [np.mean([trial(e, 90 + i)["train_loss"] for i in range(2)]) for e in etas] if len(etas) > 1 else [0.0]
                    eta = etas[int(np.argmin(np.nan_to_num(scores, nan=np.inf)))]
                    got = pd.DataFrame([trial(eta, i) for i in range(seeds)])
                avg, sd = got.mean(), got.std(ddof=0)
                yield pd.DataFrame([{
                    "name": name, "method": s["method"], "W": s["workers"], "k": s.get("k", 0), "P": s.get("p", 0), "r": s.get("rows", 0), "c": s.get("cols", 0), "eta": eta, "seeds": seeds,
                    "train_loss": avg.train_loss, "train_loss_sd": sd.train_loss, "accuracy": avg.accuracy, "accuracy_sd": sd.accuracy, "updated": avg.updated, "numbers": avg.numbers, "factor": avg.factor,
                }])

    jobs = spark.createDataFrame([(json.dumps(s),) for s in settings], "setting string").repartition(min(len(settings), 64))
    return jobs.mapInPandas(run, RESULT)


def sparse_rows(t: pa.Table, width: int) -> tuple[SIM.SparseRows, np.ndarray]:
    """Normalised rows of (coord, n), and their labels."""
    flat = lambda c: np.concatenate([x.flatten().to_numpy() for x in t.column(c).chunks] or [np.zeros(0, np.int32)])
    sizes = np.concatenate([x.value_lengths().to_numpy() for x in t.column("coord").chunks] or [np.zeros(0, np.int32)])
    value = flat("n").astype(float)
    norm = np.sqrt(np.bincount(np.repeat(np.arange(len(sizes)), sizes), value**2, minlength=len(sizes)))
    value *= 4 / np.repeat(np.maximum(norm, 1), sizes)
    return SIM.SparseRows(np.r_[0, np.cumsum(sizes, dtype=np.int64)], flat("coord").astype(np.int64), value, width), t.column("y").to_numpy()


def whole_sweep(rows, n: int, width: int, classes: int, settings: list[dict]):
    """``sweep`` of softmax models on any number of sparse rows: no task or driver holds more than the rows that a seed's steps draw.

    Every setting runs with each step size on all seeds; one pass over all rows measures all models, then each setting keeps its best step size.
    """
    spark, cut = rows.sparkSession, int(n * 0.8)
    steps, batch = settings[0]["steps"], settings[0]["batch"]
    kind = lambda: SIM.Softmax(width, classes)
    model = "setting int, eta double, seed int, good boolean, w binary, updated double, numbers double, factor double"

    def play(seed, t, draw):
        data, out = sparse_rows(t, width), []
        for i, s in enumerate(settings):
            s = {k: v for k, v in s.items() if k not in ("name", "etas")}
            for eta in settings[i]["etas"]:
                with np.errstate(all="ignore"):
                    got = SIM.simulate(kind(), data, data, eta=eta, seed=seed, draw=draw, measure=False, **s)
                out.append({"setting": i, "eta": eta, "seed": seed, "good": got["good"], "w": got["w"].tobytes(), **{k: got[k] for k in ("updated", "numbers", "factor")}})
        return pa.Table.from_pylist(out, pa.schema([("setting", pa.int32()), ("eta", pa.float64()), ("seed", pa.int32()), ("good", pa.bool_()), ("w", pa.binary()), ("updated", pa.float64()), ("numbers", pa.float64()), ("factor", pa.float64())]))

    models = commit(by_seed(rows.where(F.col("place") < cut), cut, [90, 91, *range(SEEDS)], steps, batch, play, model), "models")
    some = models.where("good").select("setting", "eta", "seed", "w").toArrow()  # settings * step sizes * seeds models of (width + 1) * classes numbers
    names = some.drop_columns(["w"])
    ws = np.stack([np.frombuffer(w) for w in some.column("w").to_pylist()]) if len(some) else np.zeros((0, (width + 1) * classes))
    every = ws[:, :-classes].reshape(-1, width, classes).transpose(1, 0, 2).reshape(width, -1)

    def measured(batches):
        sums = np.zeros((2, len(ws), 3))
        for b in batches:
            t = pa.Table.from_batches([b])
            (x, y), test = sparse_rows(t, width), t.column("place").to_numpy() >= cut
            for at in np.split(np.arange(len(y)), range(256, len(y), 256)):
                z = (x[at] @ every).reshape(len(at), -1, classes) + ws[:, -classes:]
                z -= z.max(2, keepdims=True)
                p = np.exp(z)
                own = np.take_along_axis(p, np.broadcast_to(y[at, None, None], (len(at), len(ws), 1)), 2)[..., 0] / p.sum(2)
                one = np.stack([-np.log(np.maximum(own, 1e-300)), p.argmax(2) == y[at, None], np.ones_like(own)], 2)
                sums[0] += one[~test[at]].sum(0)
                sums[1] += one[test[at]].sum(0)
        cols = [names.column(c).combine_chunks() for c in ("setting", "eta", "seed")]
        yield pa.RecordBatch.from_arrays([*cols, *(pa.array(v) for v in (sums[0, :, 0], sums[0, :, 2], sums[1, :, 1], sums[1, :, 2]))], ["setting", "eta", "seed", "loss", "n", "right", "m"])

    sums = rows.select("place", "coord", "n", "y").mapInArrow(measured, "setting int, eta double, seed int, loss double, n double, right double, m double")
    sums = sums.groupBy("setting", "eta", "seed").agg(*(F.sum(c).alias(c) for c in ("loss", "n", "right", "m")))
    got = models.drop("w").join(sums, ["setting", "eta", "seed"], "left")
    bad = lambda c, other: F.when(F.col("good"), c).otherwise(F.lit(other))
    got = got.select("setting", "eta", "seed", "updated", "numbers", "factor", bad(F.col("loss") / F.col("n"), float("inf")).alias("loss"), bad(F.col("right") / F.col("m"), 0.0).alias("acc"))
    tried = got.where("seed >= 90").groupBy("setting", "eta").agg(F.avg("loss").alias("score"))
    best = tried.groupBy("setting").agg(F.min(F.struct("score", "eta"))["eta"].alias("eta"))
    told = spark.createDataFrame([(i, s["name"], s["method"], s["workers"], s.get("k", 0), s.get("p", 0), s.get("rows", 0), s.get("cols", 0)) for i, s in enumerate(settings)], "setting int, name string, method string, W int, k int, P int, r int, c int")
    avg = lambda c, name: F.avg(c).alias(name)
    got = got.where("seed < 90").join(F.broadcast(best), ["setting", "eta"]).groupBy("setting", "eta").agg(
        F.count("*").cast("int").alias("seeds"), avg("loss", "train_loss"), F.stddev_pop("loss").alias("train_loss_sd"), avg("acc", "accuracy"), F.stddev_pop("acc").alias("accuracy_sd"), avg("updated", "updated"), avg("numbers", "numbers"), avg("factor", "factor"))
    return got.join(F.broadcast(told), "setting").select(*(x.split()[0] for x in RESULT.split(", ")))


MLP = {"kind": "mlp", "args": [64, 32, 10]}
MLP_D = 64 * 32 + 32 + 32 * 10 + 10
BASE = {"workers": 4, "steps": 60, "batch": 256}
K = 60


def cols_for(d: int, k: int, p: int, factor: float, rows: int = 5) -> int:
    """Columns that give the compression factor with p * k refetched values."""
    return max(1, round((2 * d / factor - p * k - k) / rows))


@query("w1_methods_char_model")
def w1_methods_char_model(spark, d):
    """Next-character model on all German texts: dense, true top-k, sketches at 20 and 40 times with two splits each."""
    data, k = char_data(spark, d)[:2], 1000
    _, f, c = data[0][0].shape
    s = [{"name": "dense", "method": "dense"}, {"name": "true_top_k", "method": "true_top_k", "k": k}]
    for factor, p, rows in ((20, 16, 5), (20, 36, 5), (40, 16, 15), (40, 26, 5)):
        s.append({"name": f"sketch_{factor}x_p{p}", "method": "sketch", "k": k, "p": p, "rows": rows, "cols": cols_for((f + 1) * c, k, p, factor, rows)})
    return sweep(spark, data, {"kind": "context_softmax", "args": [f, c]}, [BASE | {"steps": 20, "etas": (1.0,), "seeds": 2} | x for x in s])


@query("w2_hidden_layer_char_model")
def w2_hidden_layer_char_model(spark, d):
    """The same texts with a hidden layer: dense, true top-k, and a sketch at 40 times with large P."""
    data = char_data(spark, d)[:2]
    _, f, c = data[0][0].shape
    n, k = f * 8 + 8 + 8 * c + c, 80
    s = [{"name": "dense", "method": "dense"}, {"name": "true_top_k", "method": "true_top_k", "k": k}, {"name": "sketch_40x_p12", "method": "sketch", "k": k, "p": 12, "rows": 5, "cols": cols_for(n, k, 12, 40)}]
    return sweep(spark, data, {"kind": "context_mlp", "args": [f, 8, c]}, [BASE | {"steps": 20, "etas": (0.3,), "seeds": 2} | x for x in s])


@query("w3_true_top_k_sweep")
def w3_true_top_k_sweep(spark, d):
    """k from d/100 to d, with and without masking the velocity (at k = d masking removes momentum)."""
    s = [{"name": f"k={k} {'masked' if mask else 'unmasked'}", "method": "true_top_k", "k": k, "mask": mask} for k in (MLP_D // 100, MLP_D // 20, MLP_D // 4, MLP_D) for mask in (True, False)]
    return sweep(spark, teacher_data(spark, d), MLP, [BASE | x for x in s])


@query("w4_sketch_against_candidates")
def w4_sketch_against_candidates(spark, d):
    """One factor, split differently between sketch and refetched values; both ends."""
    s = [{"name": "no_sketch", "method": "random_candidates", "k": K, "p": 4}]
    s += [{"name": f"p={p}", "method": "sketch", "k": K, "p": p, "rows": 5, "cols": cols_for(MLP_D, K, p, 8)} for p in (1, 2, 4, 8)]
    return sweep(spark, teacher_data(spark, d), MLP, [BASE | x for x in s])


@query("w5_accuracy_against_compression")
def w5_accuracy_against_compression(spark, d):
    """Two k, several sketch widths and P, and the uncompressed and true top-k lines."""
    s = [{"name": "dense", "method": "dense"}]
    for k in (K // 2, K):
        s.append({"name": f"true_top_k k={k}", "method": "true_top_k", "k": k})
        s += [{"name": f"k={k} cols={c} p={p}", "method": "sketch", "k": k, "p": p, "rows": 5, "cols": c} for c in (40, 160) for p in (2, 6)]
    return sweep(spark, teacher_data(spark, d), MLP, [BASE | x for x in s])


@query("w6_workers")
def w6_workers(spark, d):
    """Sketch against local top-k for 1 to 256 workers: accuracy, updated parameters, numbers sent."""
    s = []
    for w in (1, 4, 16, 64, 256):
        s.append({"name": f"sketch W={w}", "method": "sketch", "workers": w, "k": 20, "p": 4, "rows": 5, "cols": 60})
        s.append({"name": f"local_top_k W={w}", "method": "local_top_k", "workers": w, "k": 20, "warmup": 10})
    rows, n, classes = language_rows(spark, d)
    return whole_sweep(rows, n, 512, classes, [BASE | {"batch": 512, "steps": 40, "etas": (0.1, 0.3)} | v for v in s])


@query("w7_longer_training")
def w7_longer_training(spark, d):
    """The same compression for 1 and 1.5 times the steps; the effective factor falls by 1.5."""
    one = {"method": "sketch", "k": 30, "p": 4, "rows": 5, "cols": cols_for(MLP_D, 30, 4, 17)}
    return sweep(spark, teacher_data(spark, d), MLP, [BASE | one | {"name": f"x{f}", "steps": int(60 * f)} for f in (1, 1.5)])


@query("w8_sixteen_bit_cells")
def w8_sixteen_bit_cells(spark, d):
    one = {"method": "sketch", "k": K, "p": 4, "rows": 5, "cols": 100}
    return sweep(spark, teacher_data(spark, d), MLP, [BASE | one | {"name": f"{b} bits", "cell_bits": b} for b in (32, 16)])


@query("w9_ablations")
def w9_ablations(spark, d):
    """Momentum correction, masking, error accumulation, refetching and residual rule, one at a time."""
    one = {"method": "sketch", "k": K, "p": 4, "rows": 5, "cols": 100}
    s = [{"name": "full"}, {"name": "no_mask", "mask": False}, {"name": "no_correction", "correction": False}, {"name": "no_accumulation", "accumulate": False}, {"name": "no_refetch", "refetch": False}, {"name": "subtract", "residual": "subtract"}, {"name": "no_momentum", "m": 0.0}]
    return sweep(spark, teacher_data(spark, d), MLP, [BASE | one | x for x in s])


@query("w10_strongly_convex")
def w10_strongly_convex(spark, d):
    """Annealed trainer on ridge: excess risk against the closed form, by k/d and number of steps."""
    l2, grid = 1.0, [(k, t) for k in (1, 2, 4, 8) for t in (50, 200, 800)]
    rows, n = placed(X.order_features(spark, d), ["ex_id"])
    model = ridge_model(rows, l2)
    floor = model.evaluate(model.best(), None, None)[0]

    def play(seed, t, draw):
        data = np.stack([t.column(f"x{i}").to_numpy() for i in range(X.DIM)], 1), t.column("y").to_numpy()
        got = [SIM.simulate(model, data, data, "annealed", 4, steps, 64, 0.0, k=k, cols=16, seed=seed, xi=min_offset(X.DIM, k), draw=draw)["train_loss"] - floor for k, steps in grid]
        k, steps = zip(*grid, strict=True)
        return pa.table({"k": pa.array(k, pa.int32()), "T": pa.array(steps, pa.int32()), "excess": pa.array(got)})

    got = by_seed(rows, n, range(SEEDS), max(t for _, t in grid), 64, play, "k int, T int, excess double")
    return got.groupBy("k", "T").agg(F.avg("excess").alias("excess"), F.stddev_pop("excess").alias("sd"))


def ridge_model(rows, l2: float) -> SIM.RidgeByMoments:
    """Ridge with the moments of all rows, in one aggregation."""
    x = [F.col(f"x{i}") for i in range(X.DIM)] + [F.col("y")]
    sums = rows.agg(F.count("*"), *(F.sum(a * b) for a in x for b in x)).first()
    m = np.array(sums[1:], float).reshape(X.DIM + 1, X.DIM + 1)
    return SIM.RidgeByMoments(X.DIM, l2, sums[0], m[:-1, :-1], m[:-1, -1], m[-1, -1])


def char_settings(f: int, c: int) -> list[dict]:
    """Two models (one as large as the contexts allow, one with a hidden layer) by the methods of the score table."""
    one, two = (f + 1) * c, f * 8 + 8 + 8 * c + c
    out = []
    for model, d, k, shapes in (("softmax", one, 1000, ((20, 36, 5), (40, 16, 15))), ("hidden", two, 80, ((40, 12, 5),))):
        base = {"model": model, "d": d, "workers": 4, "steps": 20, "batch": 256, "eta": 1.0 if model == "softmax" else 0.3}
        out += [base | {"name": "dense", "method": "dense"}, base | {"name": "true_top_k", "method": "true_top_k", "k": k}]
        out += [base | {"name": f"sketch_{x}x", "method": "sketch", "k": k, "p": p, "rows": r, "cols": cols_for(d, k, p, x, r)} for x, p, r in shapes]
    return out


RUNS = "model string, name string, method string, d long, r int, c int, P int, k int, factor double, train_loss double, test_loss double, curve array<double>, classes array<int>"


def char_runs(spark, train, test):
    """One run of each setting on all places: its measures, curve, and the letter it expects in each context."""
    _, f, c = train[0].shape

    def run(frames):
        for pdf in frames:
            for text in pdf["setting"]:
                s = json.loads(text)
                model, name, d = s.pop("model"), s.pop("name"), s.pop("d")
                net = SIM.ContextSoftmax(f, c) if model == "softmax" else SIM.ContextMlp(f, 8, c)
                with np.errstate(all="ignore"):
                    got = SIM.simulate(net, train, test, keep=True, **s)
                row = {"model": model, "name": name, "method": s["method"], "d": d, "r": s.get("rows", 0), "c": s.get("cols", 0), "P": s.get("p", 0), "k": s.get("k", 0)}
                yield pd.DataFrame([row | {x: got[x] for x in ("factor", "train_loss", "test_loss", "curve")} | {"classes": net.best_classes(got["w"]).astype(np.int32)}])

    jobs = spark.createDataFrame([(json.dumps(s),) for s in char_settings(f, c)], "setting string")
    return commit(jobs.repartition(7).mapInPandas(run, RUNS), "char-runs")


def expected_text_bleu(spark, d, runs, known: np.ndarray):
    """(model, name, bleu): held-out texts against the characters that each run expects, given the true ones before.

    Every character is a token; n-grams up to four are clipped inside a document.
    """
    rows = runs.select("model", "name", "classes").toArrow().to_pylist()  # one short array per setting
    tables = [(r["model"], r["name"], np.r_[known, np.full(len(r["classes"]), -1)][np.array(r["classes"])]) for r in rows]

    def grams(p: np.ndarray, n: int) -> np.ndarray:
        out = p[: len(p) - n + 1].astype(np.int64)
        for j in range(1, n):
            out = (out * 1_000_003 + p[j : len(p) - n + 1 + j] + 7) % (2**61 - 1) % (2**40)
        return out

    def run(batches):
        sums = {(m, x, n): [0, 0] for m, x, _ in tables for n in range(1, 5)}
        for b in batches:
            for text in b.column("t").to_pylist():
                ctx, point = char_places(text)
                for n in range(1, 5):
                    want, wanted = np.unique(grams(point, n), return_counts=True) if len(point) >= n else (np.zeros(0, np.int64),) * 2
                    for m, x, letters in tables:
                        have, had = np.unique(grams(letters[ctx], n), return_counts=True) if len(point) >= n else (np.zeros(0, np.int64),) * 2
                        at = np.minimum(np.searchsorted(want, have), max(len(want) - 1, 0))
                        hit = want[at] == have if len(want) else np.zeros(0, bool)
                        own = sums[m, x, n]
                        own[0] += int(np.minimum(had, wanted[at])[hit].sum()) if len(want) else 0
                        own[1] += int(had.sum())
        rows = [(*k, *v) for k, v in sums.items()]
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], ["model", "name", "n", "matched", "total"])

    pieces = char_documents(spark, d).where("test").select("t").mapInArrow(run, "model string, name string, n long, matched long, total long")
    pieces = pieces.groupBy("model", "name", "n").agg(F.sum("matched").alias("matched"), F.sum("total").alias("total"))
    log = F.log(F.col("matched") / F.greatest("total", F.lit(1)))
    # candidate and reference are equally long: no brevity penalty
    return pieces.groupBy("model", "name").agg(F.when(F.min("matched") > 0, F.exp(F.avg(log)) * 100).otherwise(0.0).alias("bleu"))


@query("w9_score_summary")
def w9_score_summary(spark, d):
    """The score table: method, sketch shape, P, k, compression factor, BLEU of held-out German texts, for two models."""
    train, test, known = char_data(spark, d)
    runs = char_runs(spark, train, test)
    rows = runs.drop("curve", "classes").join(expected_text_bleu(spark, d, runs, known), ["model", "name"])
    return rows.select("model", "name", "d", "r", "c", "P", "k", F.round("factor", 2).alias("factor"), "train_loss", "test_loss", F.round("bleu", 3).alias("bleu"))


@query("w1_learning_curves")
def w1_learning_curves(spark, d):
    """Training loss along the steps, and the steps each method takes to the level that true top-k ends at."""
    train, test, _ = char_data(spark, d)
    runs = char_runs(spark, train, test)
    goal = runs.where("method = 'true_top_k'").select("model", F.element_at("curve", -1).alias("goal"))
    rows = runs.join(F.broadcast(goal), "model").select("model", "name", F.posexplode("curve").alias("t", "train_loss"), "goal")
    first = F.min(F.when(F.col("train_loss") <= F.col("goal"), F.col("t") + 1)).over(Window.partitionBy("model", "name"))
    return rows.select("model", "name", (F.col("t") + 1).alias("t"), "train_loss", first.alias("steps_to_goal"))
