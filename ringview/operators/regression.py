"""Linear regression on maintained moments."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.operators.covariance import Moments


@dataclass(frozen=True)
class Model:
    """Bias first, then one parameter for each feature; ``iterations`` of the last training."""

    label: str
    features: tuple[str, ...]
    theta: np.ndarray
    iterations: int

    def predict(self, **values: float) -> float:
        return float(self.theta[0] + sum(t * values[f] for t, f in zip(self.theta[1:], self.features, strict=True)))


def train(m: Moments, label: str, features: Sequence[str], theta0: np.ndarray | None = None, alpha: float | None = None, tol: float = 1e-6, max_iter: int = 10_000) -> Model:
    """Gradient descent on the matrix alone: the label's weight stays -1.  Features are scaled to unit second moment
    and the step is one over the largest eigenvalue, if not given; ``theta0`` starts where the last training ended."""
    r = m.restrict([*features, label])
    full = r.matrix() / max(r.c, 1)
    scale = np.sqrt(np.maximum(np.diag(full), 1e-300))
    scaled = full / np.outer(scale, scale)
    a, b = scaled[:-1, :-1], scaled[:-1, -1]
    step = alpha or 1 / max(np.linalg.eigvalsh(a)[-1], 1e-300)
    w = np.zeros(len(a)) if theta0 is None else np.asarray(theta0) * scale[:-1] / scale[-1]
    size = max(np.linalg.norm(b), 1e-300)
    for i in range(max_iter + 1):
        g = a @ w - b
        if np.linalg.norm(g) / size < tol or i == max_iter:
            break
        w = w - step * g
    return Model(label, tuple(features), w * scale[-1] / scale[:-1], i)


def solve(m: Moments, label: str, features: Sequence[str], ridge: float = 0.0) -> Model:
    """Normal equations."""
    r = m.restrict([*features, label])
    full = r.matrix()
    a, b = full[:-1, :-1] + ridge * np.eye(len(full) - 1), full[:-1, -1]
    return Model(label, tuple(features), np.linalg.lstsq(a, b, rcond=None)[0], 0)


def loss(m: Moments, model: Model) -> dict[str, float]:
    """Squared loss, RMSE and R2, from the moments."""
    full = m.restrict([*model.features, model.label]).matrix()
    w = np.append(model.theta, -1.0)
    total = float(w @ full @ w)
    spread = full[-1, -1] - full[0, -1] ** 2 / max(m.c, 1)
    return {"sse": total, "rmse": float(np.sqrt(max(total, 0) / max(m.c, 1))), "r2": float(1 - total / spread) if spread else 0.0}


def train_over_data(df: DataFrame, label: str, features: Sequence[str], alpha: float, iterations: int) -> Model:
    """The contrast: each step passes over the data."""
    theta = np.zeros(len(features) + 1)
    x = [F.lit(1.0), *[F.col(f).cast("double") for f in features]]
    n = df.count()
    for _ in range(iterations):
        error = sum((c * float(t) for c, t in zip(x, theta, strict=True)), F.lit(0.0)) - F.col(label).cast("double")
        g = df.agg(*[F.sum(error * c).alias(f"g{i}") for i, c in enumerate(x)]).first()
        theta = theta - alpha / n * np.array(g)
    return Model(label, tuple(features), theta, iterations)


def train_mixed(rows: DataFrame, label: str, cont: Sequence[str], cat: Sequence[str], theta0: dict | None = None, tol: float = 1e-6, max_iter: int = 10_000, most: int = 1_000_000) -> tuple[dict[tuple[str, str], float], int]:
    """One parameter for each category, on the long layout; its slots come to the driver if they are ``most`` at most.
    New categories start at 0."""
    keep = ["", *cont, *cat, label]
    part = rows.where(F.col("x").isin(keep) & F.col("y").isin(keep))
    if part.limit(most + 1).count() > most:
        raise ValueError(f"over {most} slots: select features first")
    entries: dict[tuple[tuple[str, str], tuple[str, str]], float] = {}
    for r in part.collect():
        a, b = (r["x"], r["cx"]), (r["y"], r["cy"])
        if a == ("", ""):
            a, b = ("", ""), ("", "")
        elif b == ("", ""):
            a, b = ("", ""), a
        entries[a, b] = entries[b, a] = float(r["v"])
    names = sorted({a for a, _ in entries} - {(label, "")})
    at = {n: i for i, n in enumerate(names)}
    full = np.zeros((len(names), len(names)))
    target = np.zeros(len(names))
    for (a, b), v in entries.items():
        if a in at and b in at:
            full[at[a], at[b]] = v
        elif a in at and b == (label, ""):
            target[at[a]] = v
    n = max(entries.get((("", ""), ("", "")), 1.0), 1.0)
    scale = np.sqrt(np.maximum(np.diag(full) / n, 1e-300))
    a, b = full / n / np.outer(scale, scale), target / n / scale
    step = 1 / max(np.linalg.eigvalsh(a)[-1], 1e-300)
    w = np.array([(theta0 or {}).get(k, 0.0) for k in names]) * scale
    for i in range(max_iter + 1):
        g = a @ w - b
        if np.linalg.norm(g) / max(np.linalg.norm(b), 1e-300) < tol or i == max_iter:
            break
        w = w - step * g
    return dict(zip(names, (w / scale).tolist(), strict=True)), i


def train_grouped(rel, keys: Sequence[str], label: str, features: Sequence[str]) -> DataFrame:
    """One model for each key: (keys, bias, one column for each feature), solved where the moments are."""
    names = sorted({label, *features})
    import pandas as pd

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for row in pdf.to_dict("records"):
            q = np.array([[float(row.get(f"q_{min(x, y)}_{max(x, y)}", 0)) for y in names] for x in names])
            m = Moments(tuple(names), float(row["cnt"]), np.array([float(row[f"s_{x}"]) for x in names]), q)
            out.append([row[k] for k in keys] + solve(m, label, features).theta.tolist())
        return pd.DataFrame(out, columns=[*keys, "bias", *[f"w_{f}" for f in features]])

    kinds = dict(rel.df.dtypes)
    schema = ", ".join([*(f"{k} {kinds[k]}" for k in keys), "bias double", *(f"w_{f} double" for f in features)])
    return rel.df.mapInPandas(lambda it: (fit(p) for p in it), schema)


class OnlineRegression:
    """Trains every ``every`` batches, from the last parameters or from zero; or not at all."""

    def __init__(self, label: str, features: Sequence[str], mode: str = "warm", every: int = 1):
        if mode not in ("warm", "scratch", "none"):
            raise ValueError(mode)
        self.label, self.features, self.mode, self.every = label, tuple(features), mode, every
        self.model: Model | None = None
        self.batches = self.iterations = 0

    def after_batch(self, moments: Moments) -> Model | None:
        self.batches += 1
        if self.mode != "none" and self.batches % self.every == 0:
            start = self.model.theta if self.model is not None and self.mode == "warm" else None
            self.model = train(moments, self.label, self.features, start)
            self.iterations += self.model.iterations
        return self.model
