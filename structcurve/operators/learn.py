"""Folds, scalers, the multi-task perceptron (local and distributed), ridge, and model-based search."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.vectors import logistic

_M = 1 << 31


# ---- folds --------------------------------------------------------------------------------------


def draw(key: str, seed: int = 0):
    """High bits of a linear congruence of the id: the same in every engine."""
    return F.floor(F.pmod(F.pmod(F.col(key), F.lit(_M)) * F.lit(1103515245) + F.lit(12345 + seed), F.lit(_M)) / F.lit(65536)).cast("bigint")


def kfold(df: DataFrame, k: int = 10, key: str = "structure_id", seed: int = 0) -> DataFrame:
    return df.withColumn("fold", F.pmod(draw(key, seed), F.lit(k)).cast("int"))


def holdout(df: DataFrame, share: float = 0.8, key: str = "structure_id", seed: int = 0) -> DataFrame:
    """Adds ``split``: train or test."""
    return df.withColumn("split", F.when(draw(key, seed) < F.lit(int(round(share * 32768))), "train").otherwise("test"))


def repeated_holdout(df: DataFrame, share: float = 0.8, times: int = 10, key: str = "structure_id") -> DataFrame:
    """Each row once per repetition, ``fold`` being the repetition."""
    out = df.withColumn("fold", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    seeded = F.floor(F.pmod(F.pmod(F.col(key), F.lit(_M)) * F.lit(1103515245) + F.lit(12345) + F.col("fold").cast("bigint") * F.lit(7919 * 65536), F.lit(_M)) / F.lit(65536))
    return out.withColumn("split", F.when(seeded < F.lit(int(round(share * 32768))), "train").otherwise("test"))


# ---- scalers ------------------------------------------------------------------------------------


@dataclass
class Scaler:
    """x -> (x - shift) / scale, per column."""

    shift: dict[str, float]
    scale: dict[str, float]

    def apply(self, df: DataFrame) -> DataFrame:
        return df.withColumns({c: (F.col(c) - F.lit(self.shift[c])) / F.lit(self.scale[c]) for c in self.shift})

    def inverse(self, df: DataFrame) -> DataFrame:
        return df.withColumns({c: F.col(c) * F.lit(self.scale[c]) + F.lit(self.shift[c]) for c in self.shift})


def fit_scaler(df: DataFrame, columns: list[str], how: str = "zscore") -> Scaler:
    """One aggregate; constant columns keep scale 1."""
    if how == "none":
        return Scaler({c: 0.0 for c in columns}, {c: 1.0 for c in columns})
    aggs = [(F.avg(c), F.stddev_samp(c)) if how == "zscore" else (F.min(c), F.max(c) - F.min(c)) for c in columns]
    r = df.agg(*(x.alias(f"_{i}{j}") for i, pair in enumerate(aggs) for j, x in enumerate(pair))).first()
    return Scaler({c: float(r[f"_{i}0"] or 0.0) for i, c in enumerate(columns)}, {c: float(r[f"_{i}1"] or 1.0) or 1.0 for i, c in enumerate(columns)})


# ---- perceptron ---------------------------------------------------------------------------------


@dataclass
class Mlp:
    """Logistic hidden layers, linear outputs; weights as (matrix, bias) pairs."""

    layers: list[tuple[np.ndarray, np.ndarray]]
    x_scale: tuple[np.ndarray, np.ndarray] | None = None
    y_scale: tuple[np.ndarray, np.ndarray] | None = None

    def forward(self, x: np.ndarray) -> list[np.ndarray]:
        out = [x]
        for i, (w, b) in enumerate(self.layers):
            a = out[-1] @ w + b
            out.append(a if i == len(self.layers) - 1 else 1 / (1 + np.exp(-np.clip(a, -50, 50))))
        return out

    def predict(self, x: np.ndarray) -> np.ndarray:
        z = (x - self.x_scale[0]) / self.x_scale[1] if self.x_scale else x
        y = self.forward(z)[-1]
        return y * self.y_scale[1] + self.y_scale[0] if self.y_scale else y

    def gradients(self, x: np.ndarray, y: np.ndarray) -> tuple[float, list[tuple[np.ndarray, np.ndarray]]]:
        """Sum of halved squared errors and its gradients (sums, not means)."""
        acts = self.forward(x)
        delta = acts[-1] - y
        loss, grads = 0.5 * float((delta**2).sum()), []
        for i in range(len(self.layers) - 1, -1, -1):
            grads.append((acts[i].T @ delta, delta.sum(axis=0)))
            if i:
                delta = (delta @ self.layers[i][0].T) * acts[i] * (1 - acts[i])
        return loss, grads[::-1]

    def flat(self) -> np.ndarray:
        return np.concatenate([p.ravel() for layer in self.layers for p in layer])


def new_mlp(sizes: list[int], seed: int = 0) -> Mlp:
    rng = np.random.default_rng(seed)
    return Mlp([(rng.normal(scale=math.sqrt(1.0 / max(1, a)), size=(a, b)), np.zeros(b)) for a, b in zip(sizes, sizes[1:])])


@dataclass
class MlpConfig:
    hidden: tuple[int, ...] = (32, 16)
    rate: float = 0.01
    batch: int | None = 64
    epochs: int = 150
    seed: int = 0
    scale: str = "zscore"
    decay: float = 1e-4
    optimiser: str = "adam"


def _scales(v: np.ndarray, how: str) -> tuple[np.ndarray, np.ndarray]:
    if how == "minmax":
        lo, span = v.min(axis=0), v.max(axis=0) - v.min(axis=0)
    elif how == "zscore":
        lo, span = v.mean(axis=0), v.std(axis=0, ddof=1) if len(v) > 1 else np.ones(v.shape[1])
    else:
        lo, span = np.zeros(v.shape[1]), np.ones(v.shape[1])
    return lo, np.where(span > 0, span, 1.0)


class _Step:
    def __init__(self, rate: float, optimiser: str):
        self.rate, self.optimiser, self.t, self.state = rate, optimiser, 0, {}

    def __call__(self, layers, grads):
        self.t += 1
        out = []
        for i, (layer, grad) in enumerate(zip(layers, grads)):
            new = []
            for j, (p, g) in enumerate(zip(layer, grad)):
                if self.optimiser == "adam":
                    m, v = self.state.get((i, j), (np.zeros_like(p), np.zeros_like(p)))
                    m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
                    self.state[i, j] = m, v
                    new.append(p - self.rate * (m / (1 - 0.9**self.t)) / (np.sqrt(v / (1 - 0.999**self.t)) + 1e-8))
                else:
                    new.append(p - self.rate * g)
            out.append(tuple(new))
        return out


def train_local(x: np.ndarray, y: np.ndarray, config: MlpConfig) -> Mlp:
    """Mini-batch descent in numpy; inputs and targets are normalised by the training rows."""
    return train_side_by_side(x, y, [x.shape[1]], config)[0]


def train_side_by_side(x: np.ndarray, y: np.ndarray, ks: list[int], config: MlpConfig) -> list[Mlp]:
    """A model for the first k inputs, for each k, all on the same batches: their layers are stacked, so a step costs
    little more than that of one model.  Inputs that a model lacks have weight 0 throughout."""
    xs, ys = _scales(x, config.scale), _scales(y, config.scale)
    xn, yn = (x - xs[0]) / xs[1], (y - ys[0]) / ys[1]
    models = [new_mlp([k, *config.hidden, y.shape[1]], config.seed) for k in ks]
    sizes = [x.shape[1], *config.hidden, y.shape[1]]
    shapes = [s for a, b in zip(sizes, sizes[1:]) for s in ((len(ks), a, b), (len(ks), 1, b))]
    edges = np.cumsum([0, *(int(np.prod(s)) for s in shapes)])
    views = lambda flat: [flat[lo:hi].reshape(s) for lo, hi, s in zip(edges, edges[1:], shapes)]
    held, grad, known, decay = (np.zeros(edges[-1]) for _ in range(4))
    weights, grads = views(held), views(grad)
    known += 1.0
    for d in views(decay)[::2]:
        d[...] = config.decay  # of matrices, not of biases
    for i, (k, model) in enumerate(zip(ks, models)):
        views(known)[0][i, k:] = 0.0
        for j, (w, b) in enumerate(model.layers):
            weights[2 * j][i, : len(w)], weights[2 * j + 1][i, 0] = w, b
    masked = bool((known == 0).any())
    m, v, t = np.zeros(edges[-1]), np.zeros(edges[-1]), 0
    rng, size, last = np.random.default_rng(config.seed + 1), config.batch or len(xn), len(sizes) - 2
    for _ in range(config.epochs):
        order = rng.permutation(len(xn))
        for lo in range(0, len(order), size):
            rows = order[lo : lo + size]
            acts = [xn[rows]]
            for i in range(last + 1):
                a = np.matmul(acts[-1], weights[2 * i])
                a += weights[2 * i + 1]
                if i < last:
                    np.minimum(np.maximum(a, -50, out=a), 50, out=a)
                    np.exp(np.negative(a, out=a), out=a)
                    a += 1
                    np.divide(1, a, out=a)
                acts.append(a)
            delta = acts[-1] - yn[rows]
            for i in range(last, -1, -1):
                np.matmul(np.swapaxes(acts[i], -1, -2), delta, out=grads[2 * i])
                np.sum(delta, axis=1, keepdims=True, out=grads[2 * i + 1])
                if i:
                    delta = np.matmul(delta, np.swapaxes(weights[2 * i], -1, -2))
                    delta *= acts[i]
                    delta *= 1 - acts[i]
            g = grad / len(rows)
            g += decay * held
            if masked:
                g *= known
            t += 1
            if config.optimiser == "adam":
                m *= 0.9
                m += 0.1 * g
                v *= 0.999
                g *= g
                g *= 0.001
                v += g
                held -= config.rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
            else:
                held -= config.rate * g
    for i, (k, model) in enumerate(zip(ks, models)):
        model.layers = [(weights[2 * j][i, : k if j == 0 else None].copy(), weights[2 * j + 1][i, 0].copy()) for j in range(last + 1)]
        model.x_scale, model.y_scale = (xs[0][:k], xs[1][:k]), ys
    return models


def train_distributed(df: DataFrame, targets: list[str], config: MlpConfig, vec: str = "vec") -> Mlp:
    """Full-batch descent over a distributed table: weights are sent, tasks return summed gradients.

    Rows never come to the driver; what does is one gradient per task, added up in a tree.
    """
    k = len(df.select(vec).first()[0])
    stats = df.agg(F.count("*").alias("n"), *(f(F.get(vec, F.lit(i))).alias(f"x{i}{s}") for i in range(k) for s, f in (("m", F.avg), ("s", F.stddev_samp))), *(f(t).alias(f"y{i}{s}") for i, t in enumerate(targets) for s, f in (("m", F.avg), ("s", F.stddev_samp)))).first()
    xs = (np.array([stats[f"x{i}m"] for i in range(k)]), np.array([stats[f"x{i}s"] or 1.0 for i in range(k)]))
    ys = (np.array([stats[f"y{i}m"] for i in range(len(targets))]), np.array([stats[f"y{i}s"] or 1.0 for i in range(len(targets))]))
    model, step = new_mlp([k, *config.hidden, len(targets)], config.seed), _Step(config.rate, config.optimiser)
    rows = df.select(vec, *targets).persist()
    sc = df.sparkSession.sparkContext
    for _ in range(config.epochs):
        sent = sc.broadcast(model.layers)

        def partial(batches, sent=sent):
            import pyarrow as pa

            own, total, loss = Mlp(sent.value), None, 0.0
            for batch in batches:
                if not batch.num_rows:
                    continue
                x = np.stack(batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1))
                y = np.stack([batch.column(i + 1).to_numpy(zero_copy_only=False) for i in range(len(ys[0]))], axis=1)
                part, grads = own.gradients((x - xs[0]) / xs[1], (y - ys[0]) / ys[1])
                flat = np.concatenate([g.ravel() for pair in grads for g in pair])
                total, loss = flat if total is None else total + flat, loss + part
            if total is not None:
                yield pa.RecordBatch.from_arrays([pa.array([loss]), pa.array([total.tolist()], pa.list_(pa.float64()))], ["loss", "g"])

        parts = rows.mapInArrow(partial, "loss double, g array<double>").rdd.map(lambda r: np.array([r[0], *r[1]])).treeReduce(lambda a, b: a + b)
        flat, grads, at = parts[1:] / stats["n"], [], 0
        for w, b in model.layers:
            grads.append((flat[at : at + w.size].reshape(w.shape) + config.decay * w, flat[at + w.size : at + w.size + b.size]))
            at += w.size + b.size
        model.layers = step(model.layers, grads)
        sent.unpersist()
    rows.unpersist()
    model.x_scale, model.y_scale = xs, ys
    return model


def mlp_predict(df: DataFrame, model: Mlp, vec: str = "vec", out: str = "pred") -> DataFrame:
    """Adds the outputs as an array, in Column arithmetic: weights are literals, no Python runs."""
    if model.x_scale is not None:
        shift, scale = (F.array(*(F.lit(float(v)) for v in s)) for s in model.x_scale)
        values = F.zip_with(F.zip_with(F.col(vec), shift, lambda a, b: a - b), scale, lambda a, b: a / b)
    else:
        values = F.col(vec)
    df = df.withColumn("_h", values)
    for i, (w, b) in enumerate(model.layers):
        rows = F.array(*(F.struct(F.array(*(F.lit(float(v)) for v in w[:, j])).alias("w"), F.lit(float(b[j])).alias("b")) for j in range(w.shape[1])))
        sums = F.transform(rows, lambda n: F.aggregate(F.zip_with(F.col("_h"), n["w"], lambda a, c: a * c), F.lit(0.0), lambda acc, v: acc + v) + n["b"])
        df = df.withColumn("_h", sums if i == len(model.layers) - 1 else F.transform(sums, logistic))
    if model.y_scale is not None:
        shift, scale = (F.array(*(F.lit(float(v)) for v in s)) for s in model.y_scale)
        df = df.withColumn("_h", F.zip_with(F.zip_with(F.col("_h"), scale, lambda a, b: a * b), shift, lambda a, b: a + b))
    return df.withColumnRenamed("_h", out)


def ridge(x: np.ndarray, y: np.ndarray, penalty: float = 1.0):
    """Closed-form linear comparison model on normalised inputs."""
    xs = _scales(x, "zscore")
    z = np.column_stack([np.ones(len(x)), (x - xs[0]) / xs[1]])
    reg = penalty * np.eye(z.shape[1])
    reg[0, 0] = 0
    beta = np.linalg.solve(z.T @ z + reg, z.T @ y)
    return lambda v: np.column_stack([np.ones(len(v)), (v - xs[0]) / xs[1]]) @ beta


# ---- cross-validation ---------------------------------------------------------------------------


def in_one_task_each(df: DataFrame, models: int, targets: list[str], fn: Callable, schema: str, vec: str = "vec") -> DataFrame:
    """All rows (structure_id, fold, vec, targets) go to each of the models' tasks, which return the batches that
    ``fn(model, ids, fold, x, y)`` yields; rows in order of their ids, as arrays."""
    rows = df.select("structure_id", "fold", vec, *targets).withColumn("_model", F.explode(F.sequence(F.lit(0), F.lit(models - 1))))

    def run(batches):
        import pyarrow as pa

        got = [b for b in batches if b.num_rows]
        if not got:
            return
        t = pa.Table.from_batches(got)
        ids = t["structure_id"].to_numpy()
        order = np.argsort(ids, kind="stable")
        x = t[vec].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)[order]
        y = np.column_stack([t[c].to_numpy() for c in targets]).astype(np.float64)[order]
        model, ids, fold = t["_model"][0].as_py(), ids[order], t["fold"].to_numpy()[order]
        del t, got, order
        yield from fn(model, ids, fold, x, y)

    return rows.repartitionById(models, F.col("_model")).mapInArrow(run, schema)


_PREDICTED = "structure_id bigint, fold int, split string, target string, calc double, pred double"


def _predicted(ids: np.ndarray, fold: int, test: np.ndarray, targets: list[str], y: np.ndarray, pred: np.ndarray):
    """Rows of predictions as Arrow batches, one for each target."""
    import pyarrow as pa

    split, n = pa.array(np.where(test, "test", "train"), pa.string()), len(ids)
    for i, name in enumerate(targets):
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.full(n, fold, np.int32)), split, pa.repeat(name, n), pa.array(y[:, i]), pa.array(pred[:, i])], ["structure_id", "fold", "split", "target", "calc", "pred"])


def cross_predict(df: DataFrame, targets: list[str], config: MlpConfig | None = None, learner: str = "mlp", folds: int = 10, splits: tuple[str, ...] = ("train", "test"), vec: str = "vec", joint: bool = True, ks: list[int] | None = None) -> DataFrame:
    """``structure_id, fold, split, target, calc, pred`` by k-fold cross-validation.

    ``df`` has structure_id, fold, vec and targets.  Every row goes to every fold's task (which trains one model),
    which is right while vectors and targets fit a task - the regime after the reduction; beyond it
    :func:`train_distributed` runs fold by fold.  ``joint=False`` trains one model per target.  With ``ks`` a task
    trains a model for the first k numbers of the vectors, for each k, and the result has a column ``k``.  The
    linear learner sends no rows anywhere: see :func:`ridge_predict`.
    """
    if learner == "ridge":
        return ridge_predict(df, targets, folds, splits, vec)
    config = config or MlpConfig()

    def one(f, ids, fold, x, y):
        import pyarrow as pa

        test = fold == f
        if test.all():
            return
        groups = [list(range(len(targets)))] if joint else [[i] for i in range(len(targets))]
        models = [train_side_by_side(x[~test], y[~test][:, g], ks or [x.shape[1]], config) for g in groups]
        wanted = np.nonzero(np.where(test, "test" in splits, "train" in splits))[0]
        for lo in range(0, len(wanted), 8192):
            at = wanted[lo : lo + 8192]
            for i, k in enumerate(ks or [x.shape[1]]):
                pred = np.zeros((len(at), len(targets)))
                for g, found in zip(groups, models):
                    pred[:, g] = found[i].predict(x[at, :k])
                for batch in _predicted(ids[at], f, test[at], targets, y[at], pred):
                    yield batch if ks is None else batch.append_column("k", pa.array(np.full(len(at), k, np.int32)))

    return in_one_task_each(df, folds, targets, one, _PREDICTED + ("" if ks is None else ", k int"), vec)


def ridge_predict(df: DataFrame, targets: list[str], folds: int = 10, splits: tuple[str, ...] = ("train", "test"), vec: str = "vec", penalty: float = 1.0) -> DataFrame:
    """The same by :func:`ridge`: each task returns counts, means and centred products of its rows by fold, from which
    the driver solves every fold's equations; rows stay in place for the prediction too."""
    import pyarrow as pa

    rows = df.select("structure_id", "fold", vec, *targets)

    def arrays(batch):
        x = batch.column(2).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
        y = np.column_stack([batch.column(3 + i).to_numpy(zero_copy_only=False) for i in range(len(targets))]).astype(np.float64)
        return batch.column(0).to_numpy(), batch.column(1).to_numpy(), x, y

    def sums(batches):
        held = {}
        for batch in batches:
            if batch.num_rows:
                _, fold, x, y = arrays(batch)
                both = np.column_stack([x, y])
                for f in np.unique(fold):
                    held[int(f)] = _merged(held.get(int(f)), _moments(both[fold == f]))
        if held:
            names = sorted(held)
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int32()), pa.array([held[f][0] for f in names], pa.int64()), pa.array([held[f][1].tobytes() for f in names], pa.binary()), pa.array([held[f][2].tobytes() for f in names], pa.binary())], ["fold", "n", "mean", "product"])

    parts: dict = {}
    for r in rows.mapInArrow(sums, "fold int, n bigint, mean binary, product binary").toArrow().to_pylist():
        mean = np.frombuffer(r["mean"])
        parts[r["fold"]] = _merged(parts.get(r["fold"]), (r["n"], mean, np.frombuffer(r["product"]).reshape(len(mean), -1)))
    fits = {}
    for f in range(folds):
        whole = None
        for other in sorted(parts):
            whole = whole if other == f else _merged(whole, parts[other])
        if whole is not None:
            n, mean, product = whole
            k = len(mean) - len(targets)
            scale = np.sqrt(np.diag(product)[:k] / (n - 1)) if n > 1 else np.ones(k)
            scale = np.where(scale > 0, scale, 1.0)
            beta = np.linalg.solve(product[:k, :k] / np.outer(scale, scale) + penalty * np.eye(k), product[:k, k:] / scale[:, None])
            fits[f] = mean[:k], scale, beta, mean[k:]

    def predict(batches):
        for batch in batches:
            ids, fold, x, y = arrays(batch)
            for f, (shift, scale, beta, level) in fits.items():
                test = fold == f
                at = np.nonzero(np.where(test, "test" in splits, "train" in splits))[0]
                if len(at):
                    yield from _predicted(ids[at], f, test[at], targets, y[at], (x[at] - shift) / scale @ beta + level)

    return rows.mapInArrow(predict, _PREDICTED)


def _moments(v: np.ndarray) -> tuple[int, np.ndarray, np.ndarray]:
    mean = v.mean(axis=0)
    return len(v), mean, (v - mean).T @ (v - mean)


def _merged(a, b):
    """Count, means and centred products of two sets of rows together."""
    if a is None:
        return b
    n, gap = a[0] + b[0], b[1] - a[1]
    return n, a[1] + gap * (b[0] / n), a[2] + b[2] + np.outer(gap, gap) * (a[0] * b[0] / n)


# ---- search -------------------------------------------------------------------------------------


@dataclass
class Space:
    """Priors: name -> ('uniform', lo, hi) | ('loguniform', lo, hi) | ('quniform', lo, hi, q) | ('choice', options)."""

    dims: dict[str, tuple]

    def sample(self, rng: np.random.Generator) -> dict:
        return {k: self._one(d, rng) for k, d in self.dims.items()}

    @staticmethod
    def _one(d: tuple, rng: np.random.Generator):
        kind = d[0]
        if kind == "choice":
            return d[1][int(rng.integers(len(d[1])))]
        if kind == "loguniform":
            return float(np.exp(rng.uniform(np.log(d[1]), np.log(d[2]))))
        v = float(rng.uniform(d[1], d[2]))
        return int(round(v / d[3]) * d[3]) if kind == "quniform" else v

    def near(self, name: str, value, rng: np.random.Generator):
        """A draw around a value that did well; choices are kept or redrawn."""
        d = self.dims[name]
        if d[0] == "choice":
            return value if rng.random() < 0.8 else self._one(d, rng)
        lo, hi = (np.log(d[1]), np.log(d[2])) if d[0] == "loguniform" else (d[1], d[2])
        centre = np.log(value) if d[0] == "loguniform" else value
        v = float(np.clip(rng.normal(centre, (hi - lo) / 8), lo, hi))
        v = float(np.exp(v)) if d[0] == "loguniform" else v
        return int(round(v / d[3]) * d[3]) if d[0] == "quniform" else v

    def density(self, name: str, value, seen: list) -> float:
        """Kernel density of a value among seen ones, mixed with the prior."""
        d = self.dims[name]
        if d[0] == "choice":
            return (sum(s == value for s in seen) + 1) / (len(seen) + len(d[1]))
        to = np.log if d[0] == "loguniform" else float
        lo, hi = to(d[1]), to(d[2])
        width = max((hi - lo) / 8, 1e-12)
        z = (np.array([to(s) for s in seen]) - to(value)) / width
        return (float(np.exp(-0.5 * z**2).sum()) / (width * math.sqrt(2 * math.pi)) + 1 / max(hi - lo, 1e-12)) / (len(seen) + 1)


@dataclass
class Search:
    best: dict
    loss: float
    trials: list[tuple[int, dict, float]] = field(default_factory=list)

    def table(self, spark: SparkSession) -> DataFrame:
        import json

        rows, low = [], math.inf
        for i, p, v in self.trials:
            low = min(low, v)
            rows.append((i, json.dumps(p, sort_keys=True), float(v), float(low)))
        return spark.createDataFrame(rows, "trial int, params string, loss double, best double")


def smbo_search(space: Space, objective: Callable[[list[dict]], list[float]], n_trials: int = 24, gamma: float = 0.25, seed: int = 0, start: int = 8, per_round: int = 4, method: str = "smbo") -> Search:
    """Sequential model-based search: candidates are drawn near the few best trials and ranked by the ratio
    of densities of good to other trials; ``method='random'`` is the ablation.

    ``objective`` gets a round of settings at once, so that a round is one distributed job.
    """
    rng, trials = np.random.default_rng(seed), []
    while len(trials) < n_trials:
        want = min(per_round if len(trials) >= start else start - len(trials), n_trials - len(trials))
        if method == "random" or len(trials) < start:
            batch = [space.sample(rng) for _ in range(want)]
        else:
            ranked = sorted(trials, key=lambda t: t[2])
            cut = min(25, max(2, math.ceil(2 * gamma * math.sqrt(len(ranked)))))  # few: a wide set of good trials hides the best choices
            good, rest = [t[1] for t in ranked[:cut]], [t[1] for t in ranked[cut:]]
            # one setting of a round comes from the prior alone: a wrong choice that did well early cannot lock the search
            batch = [space.sample(rng)] if want > 1 else []
            while len(batch) < want:
                # each pick has a pool of its own, so that a round's picks differ
                pool = []
                for i in range(32):
                    base = good[int(rng.integers(len(good)))]
                    c = space.sample(rng) if i % 5 == 0 else {k: space.near(k, base[k], rng) for k in space.dims}
                    score = sum(math.log(space.density(k, c[k], [g[k] for g in good]) / space.density(k, c[k], [r[k] for r in rest])) for k in space.dims)
                    pool.append((score, i, c))
                batch.append(max(pool)[2])
        for p, v in zip(batch, objective(batch)):
            trials.append((len(trials), p, v))
    best = min(trials, key=lambda t: t[2])
    return Search(best[1], best[2], trials)
