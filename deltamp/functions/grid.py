"""Integer arithmetic on a fixed grid: sums are exact in any order, so both engines agree bit for bit."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

DIMS = 64  # the width of the given embeddings and of every layer
SCALE = 1024


def quantise(x: Column) -> Column:
    return F.floor(x.cast("double") * SCALE + 0.5).cast("long")


def mean(total: Column, n: Column) -> Column:
    """Half-up integer mean, zero without messages."""
    return F.when(n > 0, F.floor(total.cast("double") / n + 0.5).cast("long")).otherwise(F.lit(0).cast("long"))


def weights(layer: int, dims: int = DIMS) -> tuple[list[list[int]], list[list[int]], list[int]]:
    """Pinned integer weights of a layer: own, neighbour and bias (the rules in FIXTURES.md)."""
    own = [[(7 * i + 3 * j + 4 * layer) % 5 - 2 for j in range(dims)] for i in range(dims)]
    other = [[(3 * i + 2 * j + layer) % 5 - 2 for j in range(dims)] for i in range(dims)]
    return own, other, [i % 3 - 1 for i in range(dims)]


def dense(own: np.ndarray, other: np.ndarray, layer: int) -> np.ndarray:
    """relu(own weights * x + neighbour weights * m + bias), put back on the grid, for rows of integers.

    Doubles hold every product and sum exactly, so a matrix product gives the integers' own result.
    """
    ws, wn, b = (np.array(w, np.float64) for w in weights(layer, own.shape[1]))
    h = own.astype(np.float64) @ ws.T + other.astype(np.float64) @ wn.T + b
    return np.maximum(0, np.floor(h / 4.0 + 0.5)).astype(np.int64)


def update_sql(layer: int, x: str = "x", m: str = "m", dims: int = DIMS) -> list[str]:
    """The same as SQL text over columns x0.. and m0.. ."""
    ws, wn, b = weights(layer, dims)
    return [f"greatest(CAST(0 AS BIGINT), CAST(floor(CAST({b[i]} + {' + '.join(f'({ws[i][j]}) * {x}{j} + ({wn[i][j]}) * {m}{j}' for j in range(dims))} AS DOUBLE) / 4.0 + 0.5) AS BIGINT))" for i in range(dims)]


def mean_sql(total: str, n: str) -> str:
    return f"CASE WHEN {n} > 0 THEN CAST(floor(CAST({total} AS DOUBLE) / {n} + 0.5) AS BIGINT) ELSE 0 END"
