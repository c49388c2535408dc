"""Distances and angles. The one place where squared distances, slack and degrees are converted."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))


def sq_l2(a: Column, b: Column) -> Column:
    """Squared Euclidean distance of two array columns, in double."""

    def square(x, y):
        d = x.cast("double") - y.cast("double")
        return d * d

    return F.aggregate(F.zip_with(a, b, square), F.lit(0.0), lambda s, x: s + x)


def distance(a: Column, b: Column, metric: str = "l2") -> Column:
    """'l2', 'sq_l2', 'cosine' (1 - cosine) or 'inner' (minus the inner product); smaller is nearer for all."""
    if metric == "sq_l2":
        return sq_l2(a, b)
    if metric == "l2":
        return F.sqrt(sq_l2(a, b))
    if metric == "inner":
        return -dot(a, b)
    if metric == "cosine":
        return 1 - dot(a, b) / F.nullif(norm(a) * norm(b), F.lit(0.0))
    raise ValueError(f"unknown metric {metric}")


def apex_angle(dpa2: Column, dpb2: Column, dab2: Column) -> Column:
    """Degrees at p between p->a and p->b from three squared distances; 0 where a side has no length."""
    cos = (dpa2 + dpb2 - dab2) / (2 * F.sqrt(dpa2) * F.sqrt(dpb2))
    return F.when((dpa2 == 0) | (dpb2 == 0), F.lit(0.0)).otherwise(F.degrees(F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), cos)))))


def apex_angle_np(dpa2, dpb2, dab2):
    side = 2 * np.sqrt(dpa2) * np.sqrt(dpb2)
    with np.errstate(divide="ignore", invalid="ignore"):
        cos = np.where(side == 0, 1.0, (dpa2 + dpb2 - dab2) / np.where(side == 0, 1.0, side))
    return np.degrees(np.arccos(np.clip(cos, -1.0, 1.0)))


def sq_l2_np(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """All squared distances between the rows of two double matrices, by direct differences (block product only selects elsewhere)."""
    return ((x[:, None, :] - y[None, :, :]) ** 2).sum(-1)


def sq_l2_rows(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    d = x - y
    return np.einsum("...i,...i->...", d, d)


def sq_l2_pairs(x: np.ndarray, a: np.ndarray, b: np.ndarray, numbers: int = 2_000_000) -> np.ndarray:
    """Squared distances of rows a[i] and b[i]; of the rows only ``numbers`` components a side are laid out at once."""
    out, size = np.empty(len(a)), max(1, numbers // max(1, x.shape[1]))
    for at in range(0, len(a), size):
        out[at : at + size] = sq_l2_rows(x[a[at : at + size]], x[b[at : at + size]])
    return out
