"""Metric registry and vector expressions that stay inside the JVM."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def literal_vector(values: Sequence[float]) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


def doubles(v: Column) -> Column:
    return v.cast("array<double>")


def _fold(a: Column, b: Column, step: Callable[[Column, Column], Column]) -> Column:
    pairs = F.zip_with(doubles(a), doubles(b), step)
    return F.aggregate(pairs, F.lit(0.0), lambda acc, x: acc + x)


def dot(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: x * y)


def l2_norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def unit(a: Column) -> Column:
    """The vector divided by its norm; null for a zero vector."""
    n = l2_norm(a)
    return F.when(n > 0, F.transform(doubles(a), lambda x: x / n))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (l2_norm(a) * l2_norm(b))


def cosine_distance(a: Column, b: Column) -> Column:
    return F.lit(1.0) - cosine(a, b)


def squared_l2(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: (x - y) * (x - y))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(squared_l2(a, b))


def l1(a: Column, b: Column) -> Column:
    return _fold(a, b, lambda x, y: F.abs(x - y))


def linf(a: Column, b: Column) -> Column:
    return F.array_max(F.zip_with(doubles(a), doubles(b), lambda x, y: F.abs(x - y)))


def sign_hamming(a: Column, b: Column) -> Column:
    """Number of positions at which the signs differ (0 counts as positive)."""
    return _fold(a, b, lambda x, y: ((x < 0) != (y < 0)).cast("double"))


def metric_expr(step: Callable[[Column, Column], Column]) -> Callable[[Column, Column], Column]:
    """A metric from any expression over two components, summed over the positions."""
    return lambda a, b: _fold(a, b, step)


def unrolled_dot(a: Column, values: Sequence[float]) -> Column:
    """Inner product with a fixed vector as one flat sum, compiled by whole-stage codegen.

    For short vectors only: generated methods have a size limit.
    """
    if len(values) > 64:
        raise ValueError("unrolled products are for at most 64 dimensions")
    total = F.lit(0.0)
    for i, v in enumerate(values):
        total = total + a.getItem(i).cast("double") * F.lit(float(v))
    return total


def unrolled_norm(a: Column, dim: int) -> Column:
    """Length of a vector of a known, small dimension as one flat sum."""
    total = F.lit(0.0)
    for i in range(dim):
        x = a.getItem(i).cast("double")
        total = total + x * x
    return F.sqrt(total)


def is_vector(v: Column, dim: int) -> Column:
    """Whether the value is a vector of the dimension without null and NaN components."""
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x))
    return F.coalesce(v.isNotNull() & (F.size(v) == dim) & ~bad, F.lit(False))


def sparse_dot(a_indices: Column, a_values: Column, b: dict[int, float]) -> Column:
    """Inner product of a sparse vector with a sparse literal: work only for non-zero components."""
    if not b:
        return F.lit(0.0)
    table = F.create_map(*[F.lit(x) for pair in b.items() for x in (int(pair[0]), float(pair[1]))])
    terms = F.zip_with(a_indices, doubles(a_values), lambda i, x: x * F.coalesce(table[i], F.lit(0.0)))
    return F.aggregate(terms, F.lit(0.0), lambda acc, x: acc + x)


# ---- block kernels: scores of rows X (n x D) against queries Q (b x D), in double


def _unit_rows(m: np.ndarray) -> np.ndarray:
    n = np.sqrt(np.einsum("ij,ij->i", m, m))
    return m / np.where(n > 0, n, np.nan)[:, None]


def _differences(x: np.ndarray, q: np.ndarray, reduce: Callable[[np.ndarray], np.ndarray]) -> np.ndarray:
    out = np.empty((len(x), len(q)))
    step = max(1, (4 << 20) // max(1, x.size))
    for a in range(0, len(q), step):
        out[:, a : a + step] = reduce(x[:, None, :] - q[None, a : a + step, :])
    return out


@dataclass(frozen=True)
class Metric:
    """A similarity or distance: how the JVM and the block kernels compute it, and which way is better."""

    name: str
    column: Callable[[Column, Column], Column]
    block: Callable[[np.ndarray, np.ndarray], np.ndarray]
    larger_is_better: bool

    def order(self, score: Column) -> Column:
        return score.desc() if self.larger_is_better else score.asc()

    def within(self, score, bound: float):
        return score > bound if self.larger_is_better else score < bound


METRICS = {
    m.name: m
    for m in (
        Metric("cosine", cosine, lambda x, q: _unit_rows(x) @ _unit_rows(q).T, True),
        Metric("ip", dot, lambda x, q: x @ q.T, True),
        Metric("cosine_distance", cosine_distance, lambda x, q: 1 - _unit_rows(x) @ _unit_rows(q).T, False),
        Metric("l2", l2, lambda x, q: np.sqrt(_differences(x, q, lambda d: (d * d).sum(-1))), False),
        Metric("l1", l1, lambda x, q: _differences(x, q, lambda d: np.abs(d).sum(-1)), False),
        Metric("linf", linf, lambda x, q: _differences(x, q, lambda d: np.abs(d).max(-1)), False),
        Metric(
            "sign_hamming",
            sign_hamming,
            lambda x, q: ((x < 0)[:, None, :] != (q < 0)[None]).sum(-1).astype(float),
            False,
        ),
    )
}


def resolve(name: str | Metric) -> Metric:
    if isinstance(name, Metric):
        return name
    if name not in METRICS:
        raise KeyError(f"unknown metric {name!r}; known: {sorted(METRICS)}")
    return METRICS[name]
