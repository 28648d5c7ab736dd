"""Vector measures: folds that stay in the JVM, and Arrow blocks for wide or many vectors."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def dot(a: Column | str, b: Column | str) -> Column:
    """Inner product in double precision, folded in index order."""
    return F.aggregate(F.zip_with(_c(a), _c(b), lambda x, y: x * y), F.lit(0.0), lambda acc, x: acc + x)


def norm(a: Column | str) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column | str, b: Column | str) -> Column:
    """Cosine by folds; null where a vector is null or zero, or the result isn't a number."""
    value = F.try_divide(dot(a, b), norm(a) * norm(b))
    return F.when(F.isnan(value), F.lit(None)).otherwise(value)


def add_scaled(a: Column | str, b: Column | str, w: Column | float) -> Column:
    """a + w b, element by element."""
    w = w if isinstance(w, Column) else F.lit(float(w))
    return F.zip_with(_c(a), _c(b), lambda x, y: x + w * y)


def block(column: pd.Series) -> np.ndarray:
    """A batch of equally long arrays as one matrix."""
    return np.stack(column.to_numpy()).astype(float) if len(column) else np.zeros((0, 0))


@F.pandas_udf(T.DoubleType())
def cosine_arrow(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine over Arrow batches: one vectorised pass for a whole batch; null as in cosine()."""
    there = (a.notna() & b.notna()).to_numpy()
    out = np.full(len(a), np.nan)
    if there.any():
        x, y = block(a[there]), block(b[there])
        size = np.sqrt((x * x).sum(axis=1) * (y * y).sum(axis=1))
        with np.errstate(invalid="ignore", divide="ignore"):
            out[there] = np.where(size > 0, (x * y).sum(axis=1) / size, np.nan)
    return pd.Series(out, dtype=object).where(~np.isnan(out), None)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def mean_vector(v: pd.Series) -> list:
    """Grouped aggregate: the mean of a group's vectors."""
    return block(v.dropna()).mean(axis=0).tolist() if v.notna().any() else []
