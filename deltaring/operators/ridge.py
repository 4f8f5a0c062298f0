"""Ridge linear regression from maintained moments: batch gradient descent, resumed after each bulk."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.spec import CAT
from ..sources.store import new_folder
from .block import BlockRing
from .rings import MomentRing, View
from .sparse import SparseMomentRing

Feature = tuple[str, str | None]
ONE: Feature = ("1", None)


@dataclass
class Moments:
    """n rows; mean products of all pairs of features, the constant first. names: (attribute, category or None)."""

    n: float
    names: list[Feature]
    matrix: np.ndarray

    def index(self, name: Feature) -> int:
        return self.names.index(name)


@dataclass
class RidgeModel:
    """theta by feature (raw units, the constant under ("1", None)); loss and gradient are those of the scaled problem."""

    theta: dict[Feature, float]
    label: str
    loss: float
    iterations: int
    gradient_norm: float
    lam: float
    scaled: dict[Feature, float] = field(default_factory=dict)


#: Parameters up to this many are solved on the driver, which gets the square of it in numbers.
DRIVER_LIMIT = 4000


def collected(ring: MomentRing | SparseMomentRing | BlockRing, root: View, features: list[str], label: str) -> Moments:
    """The moments of some features and a label, on the driver; categorical features have a column per live category.

    Features are counted first and refused beyond DRIVER_LIMIT; the matrix comes as Arrow columns of numbers.
    """
    wanted = ["1", *features, label]
    if isinstance(ring, SparseMomentRing):
        e = ring.entries(ring.live(root))
        marked = lambda s: F.when(F.col(f"cat_{s}").isNotNull(), F.col(f"cat_{s}")).when(F.col(f"attr_{s}").isin([a for a, k in ring.kinds.items() if k == CAT]), "\0null")
    else:
        e = ring.entries(root)
        marked = lambda s: F.lit(None).cast("string")
    e = e.where(F.col("attr_u").isin(wanted) & F.col("attr_v").isin(wanted)).select("attr_u", marked("u").alias("cat_u"), "attr_v", marked("v").alias("cat_v"), F.col("value").cast("double").alias("value"))
    path = new_folder(e.sparkSession, "moments")
    e.write.parquet(path)
    e = e.sparkSession.read.parquet(path)
    found = e.where((F.col("attr_u") == "1") & ~F.col("attr_v").isin("1", label)).select("attr_v", "cat_v").limit(DRIVER_LIMIT + 1).collect()
    if len(found) > DRIVER_LIMIT:
        raise ValueError("too many parameters for the driver")
    names = [ONE, *sorted(((r[0], r[1]) for r in found), key=lambda f: (f[0], f[1] or "")), (label, None)]
    places = e.sparkSession.createDataFrame([(a, c, i) for i, (a, c) in enumerate(names)], "attr string, cat string, place int")
    for s in "uv":
        here = F.broadcast(places.select(F.col("attr").alias("a"), F.col("cat").alias("c"), F.col("place").alias(s)))
        e = e.join(here, (F.col(f"attr_{s}") == F.col("a")) & F.col(f"cat_{s}").eqNullSafe(F.col("c"))).drop("a", "c")
    cells = e.select("u", "v", "value").toArrow()
    u, v, value = (cells.column(i).to_numpy() for i in range(3))
    m = np.zeros((len(names), len(names)))
    m[u, v] = m[v, u] = value
    n = float(m[0, 0])
    return Moments(n, names, m / n if n else m)


def standardise(m: Moments, label: str) -> tuple[Moments, np.ndarray, np.ndarray]:
    """Centred and scaled moments (features and label without the constant), the means and the deviations.

    Taken from the moments alone: no pass over data. A feature that does not vary gets deviation 1.
    """
    mean = m.matrix[0].copy()
    cov = m.matrix - np.outer(mean, mean)
    dev = np.sqrt(np.maximum(np.diag(cov), 0.0))
    flat = dev <= 1e-12 * np.maximum(1.0, np.abs(mean))
    dev[flat] = 1.0
    scaled = cov / np.outer(dev, dev)
    scaled[flat, :] = 0.0
    scaled[:, flat] = 0.0
    return Moments(m.n, m.names[1:], scaled[1:, 1:]), mean, dev


def ridge_loss(m: Moments, theta: np.ndarray, lam: float) -> float:
    """Half the mean squared error plus half lam times the squared slopes; the label's slot of theta is -1."""
    full = np.append(theta, -1.0)
    return float(0.5 * full @ m.matrix @ full + 0.5 * lam * theta @ theta)


def ridge_gradient(m: Moments, theta: np.ndarray, lam: float) -> np.ndarray:
    full = np.append(theta, -1.0)
    return (m.matrix @ full)[:-1] + lam * theta


def _raw(m: Moments, mean: np.ndarray, dev: np.ndarray, theta: np.ndarray) -> dict[Feature, float]:
    slopes = theta * dev[-1] / dev[1:-1]
    out = dict(zip(m.names[1:-1], map(float, slopes)))
    out[ONE] = float(mean[-1] - slopes @ mean[1:-1])
    return out


def ridge_fit(moments: Moments, label: str, lam: float = 0.0, start: dict[Feature, float] | None = None, step: str | float = "auto", tol: float = 1e-10, most: int = 100_000) -> RidgeModel:
    """Descend on the standardised problem until the gradient is below tol (or after `most` steps).

    lam penalises the scaled slopes, never the constant. step "auto" is one over the greatest eigenvalue, by
    power iteration, plus lam. start: scaled slopes to go on from; a feature it lacks starts at 0.
    """
    if moments.n <= 0:
        return RidgeModel({ONE: 0.0}, label, 0.0, 0, 0.0, lam)
    s, mean, dev = standardise(moments, label)
    features = s.names[:-1]
    theta = np.array([(start or {}).get(f, 0.0) for f in features])
    if step == "auto":
        a, v = s.matrix[:-1, :-1], np.ones(len(features)) / max(1.0, len(features)) ** 0.5
        top = 0.0
        for _ in range(200):
            u = a @ v
            top = float(np.linalg.norm(u))
            if top == 0:
                break
            v = u / top
        step = 1.0 / (1.01 * top + lam) if top + lam > 0 else 1.0
    i, g = 0, ridge_gradient(s, theta, lam)
    while np.linalg.norm(g) > tol and i < most:
        theta = theta - step * g
        g = ridge_gradient(s, theta, lam)
        i += 1
    return RidgeModel(_raw(moments, mean, dev, theta), label, ridge_loss(s, theta, lam), i, float(np.linalg.norm(g)), lam, dict(zip(features, map(float, theta))))


def ridge_resume(model: RidgeModel, moments: Moments, **options) -> RidgeModel:
    """Go on from a model's parameters with new moments; new categories start at 0, dead ones are gone."""
    return ridge_fit(moments, model.label, model.lam, start=model.scaled, **options)


def ridge_closed_form(moments: Moments, label: str, lam: float = 0.0) -> RidgeModel:
    """The optimum of the same problem by solving its normal equations."""
    s, mean, dev = standardise(moments, label)
    a, b = s.matrix[:-1, :-1] + lam * np.eye(len(s.names) - 1), s.matrix[:-1, -1]
    theta = np.linalg.solve(a, b) if lam > 0 else np.linalg.lstsq(a, b, rcond=None)[0]
    return RidgeModel(_raw(moments, mean, dev, theta), label, ridge_loss(s, theta, lam), 0, float(np.linalg.norm(ridge_gradient(s, theta, lam))), lam, dict(zip(s.names[:-1], map(float, theta))))


def scaled_entries(m: Moments, label: str) -> list[tuple[str, str | None, str, str | None, float]]:
    """The entries that ridge_fit_distributed takes, from moments on the driver (tests, small problems)."""
    s, _, _ = standardise(m, label)
    return [(*a, *b, float(s.matrix[i, j])) for i, a in enumerate(s.names) for j, b in enumerate(s.names)]


def ridge_fit_distributed(entries: DataFrame, label: str, lam: float, steps: int, step: float, every: int = 5) -> DataFrame:
    """attr, cat, theta for more parameters than the driver should hold.

    entries: attr_u, cat_u, attr_v, cat_v, value of scaled mean products, both halves of the matrix, without the
    constant. Each step is a join of the matrix with the parameters and a sum; every few steps the
    parameters are written to shared storage, which cuts the plan.
    """
    spark = entries.sparkSession
    key = lambda s: F.concat_ws("\1", f"attr_{s}", F.coalesce(f"cat_{s}", F.lit("\0")))
    cells = entries.select(key("u").alias("u"), key("v").alias("v"), "value")
    path = new_folder(spark, "cells")
    cells.write.parquet(path)
    cells = spark.read.parquet(path)
    target = f"{label}\1\0"
    theta = cells.select(F.col("u").alias("f")).distinct().where(F.col("f") != target).withColumn("theta", F.lit(0.0))
    pull = cells.where((F.col("v") == target) & (F.col("u") != target)).select(F.col("u").alias("f"), F.col("value").alias("b"))
    inner = cells.where((F.col("v") != target) & (F.col("u") != target))
    for i in range(steps):
        push = inner.join(theta.withColumnRenamed("f", "v"), "v").groupBy(F.col("u").alias("f")).agg(F.sum(F.col("value") * F.col("theta")).alias("a"))
        g = F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0)) + F.lit(lam) * F.col("theta")
        theta = theta.join(push, "f", "left").join(pull, "f", "left").select("f", (F.col("theta") - F.lit(step) * g).alias("theta"))
        if (i + 1) % every == 0 or i + 1 == steps:
            path = new_folder(spark, "theta")
            theta.write.parquet(path)
            theta = spark.read.parquet(path)
    part = F.split("f", "\1")
    return theta.select(part[0].alias("attr"), F.when(part[1] != "\0", part[1]).alias("cat"), "theta")


def rmse_from_moments(moments: Moments, model: RidgeModel) -> tuple[float, float]:
    """Root mean squared error and R squared of the model over the join rows, from their moments alone."""
    full = np.array([model.theta.get(f, 0.0) for f in moments.names[:-1]] + [-1.0])
    mse = float(full @ moments.matrix @ full)
    var = float(moments.matrix[-1, -1] - moments.matrix[0, -1] ** 2)
    return max(mse, 0.0) ** 0.5, 1.0 - mse / var if var > 0 else 0.0


def prediction(model: RidgeModel) -> Column:
    """The model as a Column over a table with the features' columns; unknown categories add nothing."""
    out = F.lit(model.theta.get(ONE, 0.0))
    cats: dict[str, dict[str, float]] = {}
    for (attr, cat), t in model.theta.items():
        if attr == "1":
            continue
        if cat is None:
            out = out + F.lit(t) * F.col(attr).cast("double")
        else:
            cats.setdefault(attr, {})[cat] = t
    for attr, known in cats.items():
        table = F.create_map(*[x for c, t in known.items() for x in (F.lit(c), F.lit(t))])
        out = out + F.coalesce(F.try_element_at(table, F.coalesce(F.col(attr).cast("string"), F.lit("\0null"))), F.lit(0.0))
    return out


def predict(model: RidgeModel, df: DataFrame, name: str = "prediction") -> DataFrame:
    return df.withColumn(name, prediction(model))


def model_rows(spark, model: RidgeModel) -> DataFrame:
    """attr, cat, theta of a model."""
    rows = [(a, c, t) for (a, c), t in sorted(model.theta.items(), key=lambda x: (x[0][0], x[0][1] or ""))]
    return spark.createDataFrame(rows, "attr string, cat string, theta double")
