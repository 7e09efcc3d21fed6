"""Metrics with three faces: a Catalyst expression, a numpy kernel on batches, and DuckDB SQL for oracles."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Metric:
    """``column(a, b)`` and ``sql(a, b)`` give a distance; ``batch(X, P)`` the matrix of distances; ``load`` turns an Arrow column into what ``batch`` takes.

    Every guarantee rests on the triangle inequality, so only metrics are offered.
    """

    name: str
    column: Callable[[Column, Column], Column]
    batch: Callable[[np.ndarray, np.ndarray], np.ndarray]
    sql: Callable[[str, str], str]
    load: Callable[[pa.Array], np.ndarray]
    store: Callable[[np.ndarray], list]
    coords: str


def _matrix(column: pa.Array) -> np.ndarray:
    if not len(column):
        return np.zeros((0, 1))
    flat = column.flatten().to_numpy(zero_copy_only=False)
    if column.null_count or len(flat) % len(column):
        raise ValueError("coordinates must be lists of one length without nulls")
    return flat.reshape(len(column), -1)


def _rows(X: np.ndarray) -> list:
    return X.tolist()


def _fold(step: Callable[[Column, Column], Column], merge: Callable[[Column, Column], Column]) -> Callable[[Column, Column], Column]:
    return lambda a, b: F.aggregate(F.zip_with(a, b, step), F.lit(0).cast("bigint"), merge)


def _blockwise(f: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> Callable[[np.ndarray, np.ndarray], np.ndarray]:
    """One column of the matrix for each of the few centres: differences, never the product expansion, which breaks threshold tests."""
    return lambda X, P: np.stack([f(X, p) for p in P], axis=1) if len(P) else np.zeros((len(X), 0))


def _zip_sql(inner: str, outer: str) -> Callable[[str, str], str]:
    return lambda a, b: outer.format(f"list_transform(list_zip({a}, {b}), lambda z: {inner})")


L1 = Metric(
    "l1", _fold(lambda x, y: F.abs(x - y), lambda s, v: (s + v).cast("bigint")), _blockwise(lambda X, p: np.abs(X - p).sum(1)),
    _zip_sql("abs(z[1] - z[2])", "CAST(list_sum({}) AS BIGINT)"), _matrix, _rows, "array<bigint>",
)
L2 = Metric(
    "l2", lambda a, b: F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v)), _blockwise(lambda X, p: np.sqrt(((X - p) ** 2).sum(1))),
    _zip_sql("(z[1] - z[2]) * (z[1] - z[2])", "sqrt(list_sum({}))"), _matrix, _rows, "array<double>",
)
LINF = Metric("linf", lambda a, b: F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y))), _blockwise(lambda X, p: np.abs(X - p).max(1)), _zip_sql("abs(z[1] - z[2])", "list_max({})"), _matrix, _rows, "array<bigint>")
HAMMING = Metric(
    "hamming", _fold(lambda x, y: (x != y).cast("bigint"), lambda s, v: s + v), _blockwise(lambda X, p: (X != p).sum(1)),
    _zip_sql("CASE WHEN z[1] <> z[2] THEN 1 ELSE 0 END", "CAST(list_sum({}) AS BIGINT)"), _matrix, _rows, "array<bigint>",
)


def _unit_angle(X: np.ndarray, p: np.ndarray) -> np.ndarray:
    return np.arccos(np.clip((X * p).sum(1) / np.sqrt((X * X).sum(1) * (p * p).sum()), -1, 1))


def _dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


#: The angle between vectors; one minus the cosine is not a metric and is not offered.
ANGULAR = Metric(
    "angular", lambda a, b: F.acos(F.least(F.lit(1.0), F.greatest(F.lit(-1.0), _dot(a, b) / F.sqrt(_dot(a, a) * _dot(b, b))))), _blockwise(_unit_angle),
    lambda a, b: f"acos(least(1.0, greatest(-1.0, list_dot_product({a}, {b}) / sqrt(list_dot_product({a}, {a}) * list_dot_product({b}, {b})))))", _matrix, _rows, "array<double>",
)
#: Rankings as bits "i before j" for i < j: the number of inverted pairs.
INVERSIONS = Metric(
    "inversions", lambda a, b: F.bit_count(a.bitwiseXOR(b)).cast("bigint"), lambda X, P: np.bitwise_count(X[:, None] ^ P[None]).astype(np.int64),
    lambda a, b: f"CAST(bit_count(xor({a}, {b})) AS BIGINT)", lambda c: c.to_numpy(zero_copy_only=False).astype(np.int64), _rows, "bigint",
)


def _edit(a: str, b: str) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def _objects(column: pa.Array) -> np.ndarray:
    out = np.empty(len(column), object)
    out[:] = column.to_pylist()
    return out


LEVENSHTEIN = Metric("levenshtein", lambda a, b: F.levenshtein(a, b).cast("bigint"), lambda X, P: np.array([[_edit(x, p) for p in P] for x in X]).reshape(len(X), len(P)), lambda a, b: f"CAST(levenshtein({a}, {b}) AS BIGINT)", _objects, list, "string")


def _jaccard(a: list, b: list) -> float:
    x, y = set(a), set(b)
    return 1 - len(x & y) / len(x | y) if x | y else 0.0


#: Distance of sets; two empty sets are equal.
JACCARD = Metric(
    "jaccard", lambda a, b: F.when(F.size(F.array_union(a, b)) == 0, 0.0).otherwise(1 - F.size(F.array_intersect(a, b)) / F.size(F.array_union(a, b))),
    lambda X, P: np.array([[_jaccard(x, p) for p in P] for x in X]).reshape(len(X), len(P)),
    lambda a, b: f"CASE WHEN len(list_distinct(list_concat({a}, {b}))) = 0 THEN 0.0 ELSE 1 - len(list_distinct(list_intersect({a}, {b}))) / len(list_distinct(list_concat({a}, {b}))) END", _objects, list, "array<string>",
)


def tabulated(table: np.ndarray) -> Metric:
    """Points are class numbers; distances come from a small matrix.  Equal classes of different points are told apart by the caller's table."""
    t = np.asarray(table)
    look = lambda: F.array(*[F.array(*[F.lit(int(v)) for v in row]) for row in t.tolist()])
    values = str(t.tolist())
    return Metric("tabulated", lambda a, b: F.element_at(F.element_at(look(), (a + 1).cast("int")), (b + 1).cast("int")).cast("bigint"), lambda X, P: t[np.ix_(X, P)], lambda a, b: f"CAST(({values})[{a} + 1][{b} + 1] AS BIGINT)", lambda c: c.to_numpy().astype(np.int64), _rows, "bigint")


def path_rows() -> Metric:
    """Shortest paths: coordinates are [own position, distance to position 0, 1, ...]; the distance is a look-up."""
    return Metric(
        "paths", lambda a, b: F.element_at(a, (F.element_at(b, 1) + 2).cast("int")), lambda X, P: X[:, (P[:, 0] + 1).astype(np.int64)] if len(P) else np.zeros((len(X), 0)),
        lambda a, b: f"{a}[{b}[1] + 2]", _matrix, _rows, "array<bigint>",
    )


METRICS = {m.name: m for m in (L1, L2, LINF, HAMMING, ANGULAR, INVERSIONS, LEVENSHTEIN, JACCARD)}
