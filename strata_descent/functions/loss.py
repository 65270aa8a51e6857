"""Losses: Spark expressions over (x, y) for a model W, and NumPy kernels for Arrow batches.

W has a row of weights per class.  A loss gives its value per row and its residual r, with gradient
outer(r, x) before regularisation.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

Weights = list[list[float]]


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda u, v: u * v), F.lit(0.0), lambda s, v: s + v)


def norm2(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, v: s + v * v)


def literal(w: Weights) -> Column:
    return F.array(*(F.array(*(F.lit(float(v)) for v in row)) for row in w))


def logits(x: Column, w: Weights) -> Column:
    return F.transform(literal(w), lambda row: dot(x, row))


def softmax(scores: Column) -> Column:
    """Class probabilities; shifted by the largest score, so scores of any size are safe."""
    shifted = F.transform(F.array(scores), lambda s: F.transform(s, lambda v: F.exp(v - F.array_max(s))))[0]
    return F.transform(F.array(shifted), lambda e: F.transform(e, lambda v: v / F.aggregate(e, F.lit(0.0), lambda a, b: a + b)))[0]


def softmax_value(scores: Column, y: Column) -> Column:
    return F.transform(
        F.array(scores), lambda s: F.array_max(s) + F.log(F.aggregate(s, F.lit(0.0), lambda a, v: a + F.exp(v - F.array_max(s)))) - F.get(s, y)
    )[0]


def softmax_residual(scores: Column, y: Column) -> Column:
    return F.transform(softmax(scores), lambda p, c: p - F.when(c == y, 1.0).otherwise(0.0))


def predicted(scores: Column) -> Column:
    """The class of largest score, the lowest code among equals."""
    return (F.array_position(scores, F.array_max(scores)) - 1).cast("int")


def arrays(batch: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray]:
    """(y, X) of a batch with columns y and x."""
    x = batch.column(batch.schema.get_field_index("x"))
    return batch.column(batch.schema.get_field_index("y")).to_numpy(zero_copy_only=False), x.flatten().to_numpy(zero_copy_only=False).reshape(-1, d)


@dataclass(frozen=True)
class Loss:
    """NumPy kernels over a batch: scores S (rows x classes) and labels y."""

    name: str

    def residual(self, s: np.ndarray, y: np.ndarray) -> np.ndarray:
        return self.residual_of(s, np.eye(s.shape[1])[y])

    def residual_of(self, s: np.ndarray, onehot: np.ndarray) -> np.ndarray:
        """residual() for labels as rows of ones and zeros."""
        match self.name:
            case "softmax":
                e = np.exp(s - np.maximum.reduce(s, axis=1, keepdims=True))
                return e / np.add.reduce(e, axis=1, keepdims=True) - onehot
            case "squared":
                return s - onehot
            case "logistic":  # one against the rest
                sign = 2 * onehot - 1
                return -sign / (1 + np.exp(np.clip(sign * s, -500, 500)))
            case "squared_hinge":
                sign = 2 * onehot - 1
                return -sign * np.maximum(1 - sign * s, 0)
        raise ValueError(self.name)

    def value(self, s: np.ndarray, y: np.ndarray) -> np.ndarray:
        onehot = np.eye(s.shape[1])[y]
        sign = 2 * onehot - 1
        match self.name:
            case "softmax":
                top = s.max(axis=1)
                return top + np.log(np.exp(s - top[:, None]).sum(axis=1)) - s[np.arange(len(y)), y]
            case "squared":
                return 0.5 * ((s - onehot) ** 2).sum(axis=1)
            case "logistic":
                return np.logaddexp(0, -sign * s).sum(axis=1)
            case "squared_hinge":
                return 0.5 * (np.maximum(1 - sign * s, 0) ** 2).sum(axis=1)
        raise ValueError(self.name)


def get(name: str) -> Loss:
    if name not in ("softmax", "squared", "logistic", "squared_hinge"):
        raise ValueError(name)
    return Loss(name)
