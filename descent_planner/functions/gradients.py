"""Losses and gradients. Every gradient is a coefficient of margin and label times the features, so that a data
unit costs one scalar and the sum over units is one weighted column sum. Each has a Column and a NumPy form."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

CLAMP = 700.0


@dataclass(frozen=True)
class Gradient:
    name: str
    coefficient: Callable[[Column, Column], Column]
    loss: Callable[[Column, Column], Column]
    np_coefficient: Callable
    np_loss: Callable
    needs_signs: bool
    #: SQL over {z} and {y}, for oracles.
    sql: str
    sql_loss: str


def _clamped(t):
    return F.greatest(F.lit(-CLAMP), F.least(F.lit(CLAMP), t))


LINEAR = Gradient("linear", lambda z, y: 2 * (z - y), lambda z, y: (z - y) * (z - y), lambda z, y: 2 * (z - y), lambda z, y: (z - y) ** 2, False, "2*({z}-{y})", "({z}-{y})*({z}-{y})")
LOGISTIC = Gradient(
    "logistic",
    lambda z, y: -y / (1 + F.exp(_clamped(y * z))),
    lambda z, y: F.greatest(F.lit(0.0), -y * z) + F.log1p(F.exp(-F.abs(y * z))),
    lambda z, y: -y / (1 + np.exp(np.clip(y * z, -CLAMP, CLAMP))),
    lambda z, y: np.maximum(0, -y * z) + np.log1p(np.exp(-np.abs(y * z))),
    True,
    "-{y}/(1+exp(greatest(-700.0,least(700.0,{y}*({z})))))",
    "greatest(0.0,-{y}*({z}))+ln(1+exp(-abs({y}*({z}))))",
)
HINGE = Gradient(
    "hinge",
    lambda z, y: F.when(y * z < 1, -y).otherwise(F.lit(0.0)),
    lambda z, y: F.greatest(F.lit(0.0), 1 - y * z),
    lambda z, y: np.where(y * z < 1, -y, 0.0),
    lambda z, y: np.maximum(0.0, 1 - y * z),
    True,
    "CASE WHEN {y}*({z})<1 THEN -{y} ELSE 0.0 END",
    "greatest(0.0,1-{y}*({z}))",
)
GRADIENTS = {g.name: g for g in (LINEAR, LOGISTIC, HINGE)}
#: Task words of the language; a classification is logistic.
TASKS = {"regression": "linear", "linear": "linear", "linreg": "linear", "classification": "logistic", "logistic": "logistic", "logreg": "logistic", "svm": "hinge", "hinge": "hinge"}


def register_gradient(gradient: Gradient) -> None:
    """Adds a user's gradient under its name."""
    GRADIENTS[gradient.name] = gradient
    TASKS[gradient.name] = gradient.name


def regulariser(kind: str, lam: float, w: np.ndarray) -> np.ndarray:
    """(Sub)gradient of lam/2 |w|_2^2, lam |w|_1 or nothing."""
    if kind == "none" or lam == 0:
        return np.zeros_like(w)
    if kind == "l2":
        return lam * w
    if kind == "l1":
        return lam * np.sign(w)
    raise ValueError(f"unknown regulariser {kind}")


def penalty(kind: str, lam: float, w: np.ndarray) -> float:
    return {"none": 0.0, "l2": lam / 2 * float(w @ w), "l1": lam * float(np.abs(w).sum())}[kind]
