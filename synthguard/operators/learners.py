"""Classifiers of the utility experiments: trees, forests, boosting, linear models with and without privacy; accuracy,
agreement, and the game of telling real from synthetic."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.ml.classification import DecisionTreeClassifier, LinearSVC, LogisticRegression, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from synthguard.functions.noise import uniform
from synthguard.operators.bounded import generator, trained
from synthguard.plans.schema import Schema, categorical


def vectors(df: DataFrame, schema: Schema, target: str | None) -> DataFrame:
    """df with `features`: the codes of all attributes but the target."""
    return VectorAssembler(inputCols=[n for n in schema.names if n != target], outputCol="features").transform(df)


class Fitted:
    """A classifier that adds a column of predicted classes (double)."""

    def __init__(self, add):
        self.add = add

    def predict(self, df: DataFrame, out: str = "guess") -> DataFrame:
        return self.add(df, out)


def fit(kind: str, df: DataFrame, schema: Schema, target: str, seed: int = 1, lam: float = 1e-4) -> Fitted:
    """kind: tree, rf, adaboost, lr, svm."""
    if kind == "adaboost":
        return adaboost(df, schema, target, seed=seed)
    makers = {
        "tree": lambda: DecisionTreeClassifier(labelCol=target, maxDepth=10, maxBins=64, seed=seed),
        "rf": lambda: RandomForestClassifier(labelCol=target, numTrees=20, maxDepth=10, maxBins=64, seed=seed),
        "lr": lambda: LogisticRegression(labelCol=target, regParam=lam, maxIter=50),
        "svm": lambda: LinearSVC(labelCol=target, regParam=lam, maxIter=50),
    }
    model = makers[kind]().fit(vectors(df.select(*schema.names), schema, target))

    def add(rows: DataFrame, out: str) -> DataFrame:
        drop = [c for c in ("features", "rawPrediction", "probability") if c not in rows.columns]
        return model.transform(vectors(rows, schema, target)).withColumnRenamed("prediction", out).drop(*drop)

    return Fitted(add)


def adaboost(df: DataFrame, schema: Schema, target: str, rounds: int = 8, depth: int = 4, seed: int = 1) -> Fitted:
    """AdaBoost.M1: each round fits a weighted tree, and rows it gets right lose weight by e / (1 - e); trees vote with
    ln((1 - e) / e); a round whose weighted error e reaches one half ends it.

    A row's weight is a function of the trees so far, so it is computed in the scan and no weights are stored between rounds."""
    rows = vectors(df.select(*schema.names), schema, target)
    trees: list = []
    for r in range(rounds):
        weighted = _weigh(rows, trees, target)
        tree = DecisionTreeClassifier(labelCol=target, weightCol="_w", maxDepth=depth, maxBins=64, seed=seed + r).fit(weighted)
        wrong = F.sum(F.when(F.col("prediction") != F.col(target), F.col("_w")).otherwise(0.0)) / F.sum("_w")
        e = tree.transform(weighted).agg(wrong.alias("e")).first()["e"]
        if e is None or e >= 0.5:
            break
        trees.append((tree, math.log(max(e, 1e-10) / (1 - max(e, 1e-10)))))
        if e <= 1e-10:
            break

    def add(frame: DataFrame, out: str) -> DataFrame:
        x = vectors(frame, schema, target)
        vote = F.lit(0.0)
        names = []
        for k, (tree, lb) in enumerate(trees):
            x = tree.transform(x).withColumnRenamed("prediction", f"_v{k}").drop("rawPrediction", "probability")
            vote = vote + F.when(F.col(f"_v{k}") > 0.5, -lb).otherwise(lb)
            names.append(f"_v{k}")
        return x.withColumn(out, (vote > 0).cast("double")).drop("features", *names)

    return Fitted(add)


def _weigh(rows: DataFrame, trees, target: str) -> DataFrame:
    x, total, names = rows, F.lit(0.0), []
    for k, (tree, lb) in enumerate(trees):
        x = tree.transform(x).withColumnRenamed("prediction", f"_v{k}").drop("rawPrediction", "probability")
        total = total + F.when(F.col(f"_v{k}") == F.col(target), F.lit(lb)).otherwise(0.0)
        names.append(f"_v{k}")
    return x.withColumn("_w", F.exp(total)).drop(*names)


# --- linear models by empirical risk minimisation, with privacy by output or objective perturbation


def encoded_width(schema: Schema, target: str) -> int:
    return sum(a.card if a.kind == "categorical" else 1 for a in schema.attributes if a.name != target) + 1


def encode(batch: pd.DataFrame, schema: Schema, target: str) -> np.ndarray:
    """One-hot categories and numbers scaled to [0, 1] by the declared domains, a constant, all at norm 1 or less."""
    parts = []
    for a in schema.attributes:
        if a.name == target:
            continue
        x = batch[a.name].to_numpy()
        parts.append(np.eye(a.card)[x] if a.kind == "categorical" else (x / max(a.card - 1, 1))[:, None])
    x = np.concatenate([*parts, np.ones((len(batch), 1))], 1)
    return x / np.maximum(1.0, np.sqrt((x**2).sum(1, keepdims=True)))


def _loss(name: str, h: float = 0.5):
    """(slope of the loss at margin z, bound of its curvature, the loss, its curvature)."""
    if name == "lr":
        odds = lambda z: 1 / (1 + np.exp(np.clip(z, -500, 500)))
        return (lambda z: -odds(z)), 0.25, (lambda z: np.logaddexp(0, -z)), (lambda z: odds(z) * (1 - odds(z)))
    slope = lambda z: np.where(z > 1 + h, 0.0, np.where(z < 1 - h, -1.0, -(1 + h - z) / (2 * h)))
    value = lambda z: np.where(z > 1 + h, 0.0, np.where(z < 1 - h, 1 - z, (1 + h - z) ** 2 / (4 * h)))
    return slope, 1 / (2 * h), value, (lambda z: np.where(np.abs(1 - z) <= h, 1 / (2 * h), 0.0))


def minimise(df: DataFrame, schema: Schema, target: str, loss: str, lam: float, linear: np.ndarray | None = None, n: int | None = None, steps: int = 200) -> np.ndarray:
    """argmin of mean loss + lam/2 |w|^2 + linear.w / n by damped Newton steps; each task sends its sums of the loss, gradient
    and curvature once a step. Ends where the gradient is so small that w is within 0.01 / (n lam) of the minimum, which is
    far less than the noise of output perturbation; where `steps` do not reach that it raises, as noise is made for the minimum."""
    slope, bound, value, bend = _loss(loss)
    d = encoded_width(schema, target)
    n = n or df.count()
    linear = np.zeros(d) if linear is None else linear
    rows = df.select(*schema.names)

    def measured(w: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        def sums(batches):
            total = np.zeros(1 + d + d * d)
            for b in batches:
                x = encode(b, schema, target)
                y = np.where(b[target].to_numpy() == 1, 1.0, -1.0)
                z = y * (x @ w)
                total[0] += value(z).sum()
                total[1 : d + 1] += x.T @ (slope(z) * y)
                total[d + 1 :] += (x.T @ (x * bend(z)[:, None])).ravel()
            yield pd.DataFrame({"k": np.arange(len(total)), "s": total})

        got = rows.mapInPandas(sums, "k int, s double").groupBy("k").agg(F.sum("s").alias("s")).collect()  # 1 + d + d * d rows
        t = np.zeros(1 + d + d * d)
        for r in got:
            t[r["k"]] = r["s"]
        return t[0] / n + lam / 2 * w @ w + linear @ w / n, t[1 : d + 1] / n + lam * w + linear / n, t[d + 1 :].reshape(d, d) / n + lam * np.eye(d)

    return newton(measured, d, n, bound, steps)


def newton(measured, d: int, n: int, bound: float, steps: int) -> np.ndarray:
    """The minimum by damped steps; measured: cost, gradient and curvature at w."""
    # with damping at the bound of the curvature a step cannot fail; it is taken off as steps succeed
    w, damping = np.zeros(d), bound
    cost, g, h = measured(w)
    for _ in range(steps):
        if np.linalg.norm(g) <= min(1e-5, 0.01 / max(n, 1)):
            return w
        new = w - np.linalg.solve(h + damping * np.eye(d), g)
        at = measured(new)
        # where costs differ by rounding alone, the gradient tells
        if at[0] < cost or (at[0] <= cost + 1e-12 * abs(cost) and np.linalg.norm(at[1]) < np.linalg.norm(g)):
            w, (cost, g, h), damping = new, at, damping / 10
        else:
            damping *= 10
    if np.linalg.norm(g) <= min(1e-5, 0.01 / max(n, 1)):
        return w
    raise RuntimeError(f"{steps} steps left a gradient of {np.linalg.norm(g)}")


def minimise_arrays(x: np.ndarray, y: np.ndarray, loss: str, lam: float, linear: np.ndarray | None = None, steps: int = 200) -> np.ndarray:
    """minimise() of a sample that one task holds; y in -1, 1."""
    slope, bound, value, bend = _loss(loss)
    n, d = x.shape
    linear = np.zeros(d) if linear is None else linear

    def measured(w):
        z = y * (x @ w)
        return value(z).sum() / n + lam / 2 * w @ w + linear @ w / n, x.T @ (slope(z) * y) / n + lam * w + linear / n, x.T @ (x * bend(z)[:, None]) / n + lam * np.eye(d)

    return newton(measured, d, n, bound, steps)


def _noise(d: int, rate: float, *key) -> np.ndarray:
    """A vector of random direction whose norm has density proportional to r^(d-1) exp(-rate r); it hangs on the key, whose salt must stay secret."""
    rng = generator(*key)
    v = rng.normal(size=d)
    return v / np.linalg.norm(v) * rng.gamma(d, 1 / rate)


def private_weights(fit, n: int, d: int, loss: str, lam: float, privacy: str | None, eps: float, *key) -> np.ndarray:
    """Weights of fit(lam, linear) without privacy, or eps-private by perturbing the output or the objective."""
    if privacy is None:
        return fit(lam, None)
    if privacy == "output":
        return fit(lam, None) + _noise(d, n * lam * eps / 2, *key, loss, privacy)
    c = _loss(loss)[1]
    left = eps - math.log(1 + 2 * c / (n * lam) + c * c / (n * lam) ** 2)
    extra = 0.0
    if left <= 0:
        extra = c / (n * (math.exp(eps / 4) - 1)) - lam
        left = eps / 2
    return fit(lam + max(extra, 0.0), _noise(d, left / 2, *key, loss, privacy))


def linear_weights(df: DataFrame, schema: Schema, target: str, loss: str = "lr", lam: float = 1e-4, privacy: str | None = None, eps: float = 1.0, salt: str = "", steps: int = 200) -> np.ndarray:
    """Weights without privacy, or eps-private; loss: lr, or svm (Huber's hinge). The noise hangs on salt, a secret, and the loss."""
    if privacy is not None and not salt:
        raise ValueError("the noise needs a secret salt")
    n, d = df.count(), encoded_width(schema, target)
    return private_weights(lambda lam, push: minimise(df, schema, target, loss, lam, push, n, steps), n, d, loss, lam, privacy, eps, salt, schema.name, target)


def linear(weights: np.ndarray, schema: Schema, target: str) -> Fitted:
    names = [n for n in schema.names if n != target]

    def add(df: DataFrame, out: str) -> DataFrame:
        @F.pandas_udf("double")
        def guess(x: pd.DataFrame) -> pd.Series:
            return pd.Series((encode(x, schema, target) @ weights > 0).astype(float))

        return df.withColumn(out, guess(F.struct(*names)))

    return Fitted(add)


def choose_lambda(train: DataFrame, test: DataFrame, schema: Schema, target: str, loss: str, grid=(1e-3, 1e-4, 1e-5, 1e-6), steps: int = 200) -> float:
    """The grid value at which the model without privacy is most accurate; ties go to the larger."""
    scores = [(accuracy(linear(linear_weights(train, schema, target, loss, lam, steps=steps), schema, target), test, target), lam) for lam in grid]
    return max(scores)[1]


# --- measures


def accuracy(model: Fitted, test: DataFrame, target: str) -> float:
    return model.predict(test).agg(F.avg((F.col("guess") == F.col(target)).cast("double"))).first()[0] or 0.0


def scores(model: Fitted, reference: Fitted, test: DataFrame, target: str) -> tuple[float, float]:
    """Accuracy, and the share of test rows on which both models say the same, right or wrong; one pass."""
    both = reference.predict(model.predict(test, "guess"), "_other")
    r = both.agg(F.avg((F.col("guess") == F.col(target)).cast("double")).alias("a"), F.avg((F.col("guess") == F.col("_other")).cast("double")).alias("g")).first()
    return r["a"] or 0.0, r["g"] or 0.0


def game(real: DataFrame, other: DataFrame, schema: Schema, kind: str, salt: str, key: str = "rk") -> float:
    """Accuracy of telling real from other on held-out rows, half of each kind; 1/2 says they cannot be told apart.

    Each side gives its n rows of the smallest keyed numbers; by the same order, its first two thirds train and the rest test."""
    n = min(real.count(), other.count())
    label = with_label(schema)

    def even(df, mark):
        # the n smallest numbers: a bound that surely lets them pass, and a sort of what is left
        u = uniform(f"{salt}-{mark}", key)
        share = n / max(1, df.count())
        near = min(1.0, share + 6 * math.sqrt(share / max(1, df.count())) + 20 / max(1, df.count()))
        return df.withColumn("_u", u).where(F.col("_u") <= near).orderBy("_u").limit(n).withColumn("_real", F.lit(mark)).select(*label.names, "_u")

    mixed = even(real, 1).unionByName(even(other, 0)).cache()
    try:
        # a cut for each side: the larger side's numbers all lie below those of the smaller
        cuts = [mixed.where(F.col("_real") == mark).orderBy("_u").limit(2 * n // 3).agg(F.max("_u")).first()[0] for mark in (0, 1)]
        train = F.col("_u") <= F.when(F.col("_real") == 1, F.lit(cuts[1])).otherwise(F.lit(cuts[0]))
        return accuracy(fit(kind, mixed.where(train), label, "_real"), mixed.where(~train), "_real")
    finally:
        mixed.unpersist()


def with_label(schema: Schema) -> Schema:
    """The schema of records that are marked as real or not."""
    return Schema(schema.name + "_game", (*schema.attributes, categorical("_real", ("0", "1"))))


def play(rows: pd.DataFrame, label: Schema, kinds=("tree", "rf")) -> pd.DataFrame:
    """The game on one sample (kind, the attributes, _real, and _u, by which each side is ordered): kind, classifier, accuracy, records of a side."""
    name, got = rows["kind"].iloc[0], []
    sides = [rows[rows["_real"] == mark].sort_values("_u") for mark in (0, 1)]
    n = min(map(len, sides))
    train, test = (pd.concat([s.iloc[a:b] for s in sides]) for a, b in ((0, 2 * n // 3), (2 * n // 3, n)))
    for c in kinds if n >= 3 else ():
        got.append((name, c, float((trained(c, train, label, "_real", "game")(test) == test["_real"]).mean()), n))
    return pd.DataFrame(got, columns=["kind", "classifier", "accuracy", "records"])
