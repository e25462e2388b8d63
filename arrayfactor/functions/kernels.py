"""Covariance functions of factor rows: on small matrices in a worker, and as Spark expressions."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KINDS = ("rbf", "linear", "poly", "matern32", "matern52")


@dataclass(frozen=True)
class Kernel:
    kind: str = "rbf"
    scale: float = 1.0  # length scale
    amplitude: float = 1.0
    offset: float = 1.0
    gamma: float = 1.0
    power: int = 2
    nugget: float = 1e-6


def covariance(u: np.ndarray, v: np.ndarray, k: Kernel, same: bool = False) -> np.ndarray:
    """k of every row of u with every row of v; the nugget only where both are the same points."""
    dot = u @ v.T
    if k.kind == "linear":
        out = k.amplitude**2 * dot + k.offset
    elif k.kind == "poly":
        out = (k.gamma * dot + k.offset) ** k.power
    else:
        d2 = np.maximum((u**2).sum(1)[:, None] + (v**2).sum(1)[None, :] - 2 * dot, 0) / k.scale**2
        d = np.sqrt(d2)
        if k.kind == "rbf":
            out = np.exp(-d2 / 2)
        elif k.kind == "matern32":
            out = (1 + math.sqrt(3) * d) * np.exp(-math.sqrt(3) * d)
        elif k.kind == "matern52":
            out = (1 + math.sqrt(5) * d + 5 * d2 / 3) * np.exp(-math.sqrt(5) * d)
        else:
            raise ValueError(k.kind)
        out = k.amplitude**2 * out
    return out + k.nugget * np.eye(len(u)) if same else out


def diagonal(u: np.ndarray, k: Kernel) -> np.ndarray:
    """k of every row of u with itself."""
    if k.kind in ("linear", "poly"):
        dot = (u * u).sum(1)
        return k.amplitude**2 * dot + k.offset if k.kind == "linear" else (k.gamma * dot + k.offset) ** k.power
    return np.full(len(u), k.amplitude**2)


def row_gradient(u: np.ndarray, g: np.ndarray, k: Kernel) -> np.ndarray:
    """Gradient by the rows of u of a function whose gradient by covariance(u, u) is g."""
    g = g + g.T
    if k.kind == "linear":
        return k.amplitude**2 * (g @ u)
    if k.kind == "poly":
        w = g * (k.power * k.gamma * (k.gamma * (u @ u.T) + k.offset) ** (k.power - 1))
        return w @ u
    d2 = np.maximum((u**2).sum(1)[:, None] + (u**2).sum(1)[None, :] - 2 * (u @ u.T), 0) / k.scale**2
    d = np.sqrt(d2)
    # derivative by half the squared distance; finite at zero for every kind here
    if k.kind == "rbf":
        slope = -np.exp(-d2 / 2)
    elif k.kind == "matern32":
        slope = -3 * np.exp(-math.sqrt(3) * d)
    else:
        slope = -5 / 3 * (1 + math.sqrt(5) * d) * np.exp(-math.sqrt(5) * d)
    w = g * slope * (k.amplitude / k.scale) ** 2
    return w.sum(1)[:, None] * u - w @ u


def kernel_expr(x: Column, y: Column, k: Kernel) -> Column:
    """The same between two array columns, inside Spark."""
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda a, v: a + v)
    if k.kind in ("linear", "poly"):
        dot = total(F.zip_with(x, y, lambda a, b: a.cast("double") * b.cast("double")))
        return F.lit(k.amplitude**2) * dot + F.lit(k.offset) if k.kind == "linear" else F.pow(F.lit(k.gamma) * dot + F.lit(k.offset), F.lit(float(k.power)))
    d2 = total(F.zip_with(x, y, lambda a, b: (a.cast("double") - b.cast("double")) * (a.cast("double") - b.cast("double")))) / F.lit(k.scale**2)
    d = F.sqrt(d2)
    if k.kind == "rbf":
        out = F.exp(-d2 / 2)
    elif k.kind == "matern32":
        out = (1 + math.sqrt(3) * d) * F.exp(-math.sqrt(3) * d)
    else:
        out = (1 + math.sqrt(5) * d + 5 * d2 / 3) * F.exp(-math.sqrt(5) * d)
    return F.lit(k.amplitude**2) * out


def kernel_table(vectors: DataFrame, k: Kernel, of: DataFrame | None = None) -> DataFrame:
    """(a, b, k) of the vectors (id, vec) of a stated set ``of`` (all, for one subarray's rows) with every vector.

    The stated set is the side that is sent; it is small or given in blocks.
    """
    right, left = vectors.select(F.col("id").alias("b"), F.col("vec").alias("y")), (vectors if of is None else of).select(F.col("id").alias("a"), F.col("vec").alias("x"))
    return right.join(F.broadcast(left), F.lit(True)).select("a", "b", kernel_expr(F.col("x"), F.col("y"), k).alias("k"))
