"""Synthetic arrays: a sum of Gaussians over a grid, dense or with cells below a threshold left empty."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import ArraySpec, Dim
from ..operators.baselines import LinearIndex, build_linear
from ..operators.tree import Index, IndexConfig, build_index

Component = tuple[tuple[float, ...], tuple[tuple[float, ...], ...]]

#: Means as shares of the grid, standard deviations as shares of it; a plain example with diagonal covariances.
FIXED_2D = [((0.25, 0.25), (0.125, 0.25)), ((0.75, 0.5), (0.25, 0.125)), ((0.5, 0.875), (0.5, 0.5))]
_BUILT: dict[tuple, Index] = {}
_LINEAR: dict[tuple, LinearIndex] = {}


def random_components(dims: int, count: int, seed: int = 42, spread: tuple[float, float] = (0.05, 0.3)) -> list[Component]:
    """Random means in the unit cube and bounded symmetric positive definite covariances Q diag Q'."""
    rng = np.random.default_rng(seed)
    out = []
    for _ in range(count):
        q, _ = np.linalg.qr(rng.standard_normal((dims, dims)))
        cov = q @ np.diag(rng.uniform(*spread, dims) ** 2) @ q.T
        out.append((tuple(rng.random(dims)), tuple(map(tuple, cov))))
    return out


def scaled(shape: tuple[int, ...], parts) -> list[tuple[list[float], np.ndarray, float]]:
    """(mean, inverse covariance, factor) in cells; deviations given instead of a matrix mean a diagonal covariance."""
    out = []
    side = np.array(shape, float)
    for mean, second in parts:
        second = np.array(second, float)
        cov = np.diag(second**2) if second.ndim == 1 else second
        cov = cov * np.outer(side, side)
        out.append(((np.array(mean) * side).tolist(), np.linalg.inv(cov), 1 / math.sqrt((2 * math.pi) ** len(shape) * np.linalg.det(cov))))
    return out


def sum_gauss(spark: SparkSession, shape: tuple[int, ...], parts, threshold: float | None = None) -> DataFrame:
    """Cells d0.. and value: one arithmetic pass over a range, no shuffle."""
    n = len(shape)
    strides = [math.prod(shape[i + 1 :]) for i in range(n)]
    at = [F.floor(F.col("id") / s) % k for s, k in zip(strides, shape)]
    cells = spark.range(math.prod(shape)).select(*[a.cast("long").alias(f"d{i}") for i, a in enumerate(at)])
    value = F.lit(0.0)
    for mean, inverse, factor in scaled(shape, parts):
        form = F.lit(0.0)
        for i in range(n):
            for j in range(n):
                if inverse[i, j]:
                    form = form + F.lit(float(inverse[i, j])) * (F.col(f"d{i}") - F.lit(mean[i])) * (F.col(f"d{j}") - F.lit(mean[j]))
        value = value + F.lit(factor) * F.exp(form * -0.5)
    cells = cells.withColumn("value", value)
    return cells if threshold is None else cells.where(F.col("value") >= threshold)


#: Side of a chunk by the number of dimensions.
SIDES = {1: 64, 2: 32, 3: 8, 4: 4}


def index(spark: SparkSession, shape: tuple[int, ...], parts=None, cfg: IndexConfig | None = None, threshold: float | None = None, side: int | None = None) -> Index:
    """Index of a generated array. Chunks without a cell above the threshold have no leaf."""
    key = (spark.sparkContext.applicationId, shape, repr(parts), cfg, threshold, side)
    if key not in _BUILT:
        cells = sum_gauss(spark, shape, parts or FIXED_2D, threshold)
        _BUILT[key] = build_index(cells, spec_of(shape, side), cfg)
    return _BUILT[key]


def spec_of(shape: tuple[int, ...], side: int | None = None) -> ArraySpec:
    return ArraySpec(tuple(Dim(f"d{i}", 0, k) for i, k in enumerate(shape)), "value", (side or SIDES[len(shape)],) * len(shape))


def linear(spark: SparkSession, shape: tuple[int, ...], columns: str, parts=None, threshold: float | None = None, **options) -> LinearIndex:
    """The baselines' stored index of a generated array."""
    key = (spark.sparkContext.applicationId, shape, repr(parts), columns, threshold, tuple(sorted(options.items())))
    if key not in _LINEAR:
        spec = spec_of(shape)
        cells = sum_gauss(spark, shape, parts or FIXED_2D, threshold)
        _LINEAR[key] = build_linear(cells, spec, [*spec.names, spec.attr] if columns == "all" else [spec.attr], **options)
    return _LINEAR[key]


def sql(shape: tuple[int, ...], parts, digits: int | None = 9) -> str:
    """The same grid for DuckDB."""
    n, terms = len(shape), []
    for mean, inverse, factor in scaled(shape, parts):
        form = " + ".join(f"{float(inverse[i, j])!r}::DOUBLE * (d{i} - {float(mean[i])!r}::DOUBLE) * (d{j} - {float(mean[j])!r}::DOUBLE)" for i in range(n) for j in range(n) if inverse[i, j])
        terms.append(f"{float(factor)!r}::DOUBLE * exp(-0.5 * ({form}))")
    axes = ", ".join(f"(SELECT unnest(generate_series(0, {k - 1})) AS d{i})" for i, k in enumerate(shape))
    value = " + ".join(terms)
    return f"SELECT {', '.join(f'd{i}' for i in range(n))}, {value if digits is None else f'round({value}, {digits})'} AS value FROM {axes}"
