"""Activations, their derivatives and losses as Column builders, with NumPy twins."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

ACTIVATIONS = ("sigmoid", "relu", "tanh", "identity", "capped_relu")
#: Upper end of the capped rectifier.
CAP = 32.0


def activate(z: Column, kind: str) -> Column:
    return {
        "sigmoid": lambda: 1 / (1 + F.exp(-z)), "relu": lambda: F.greatest(z, F.lit(0.0)), "tanh": lambda: F.tanh(z), "identity": lambda: z,
        "capped_relu": lambda: F.least(F.greatest(z, F.lit(0.0)), F.lit(CAP)),
    }[kind]()


def activate_prime(z: Column, x: Column, kind: str) -> Column:
    """Derivative at z, given x = f(z); the rectifiers' derivative at their corners is 0."""
    one = F.lit(1.0)
    return {
        "sigmoid": lambda: x * (1 - x), "relu": lambda: F.when(z > 0, one).otherwise(0.0), "tanh": lambda: 1 - x * x, "identity": lambda: one,
        "capped_relu": lambda: F.when((z > 0) & (z < CAP), one).otherwise(0.0),
    }[kind]()


def keeps_zero(kind: str) -> bool:
    """Whether f(0) = 0, so that neurons without input may be left out."""
    return kind != "sigmoid"


def np_activate(z: np.ndarray, kind: str) -> np.ndarray:
    return {"sigmoid": lambda: 1 / (1 + np.exp(-z)), "relu": lambda: np.maximum(z, 0), "tanh": lambda: np.tanh(z), "identity": lambda: z, "capped_relu": lambda: np.clip(z, 0, CAP)}[kind]()


def np_prime(z: np.ndarray, x: np.ndarray, kind: str) -> np.ndarray:
    return {
        "sigmoid": lambda: x * (1 - x), "relu": lambda: (z > 0) * 1.0, "tanh": lambda: 1 - x * x, "identity": lambda: np.ones_like(z),
        "capped_relu": lambda: ((z > 0) & (z < CAP)) * 1.0,
    }[kind]()


def loss_slope(x: Column, y: Column, kind: str, outputs: int) -> Column:
    """Derivative of the loss in the output x. mse_half: half the sum of squares; mse_mean: their mean over the outputs."""
    return {"mse_half": lambda: x - y, "mse_mean": lambda: 2 * (x - y) / outputs}[kind]()


def loss_value(x: Column, y: Column, kind: str) -> Column:
    """Aggregate over the outputs of one vector."""
    square = (x - y) * (x - y)
    return {"mse_half": lambda: F.sum(square) / 2, "mse_mean": lambda: F.avg(square)}[kind]()
