"""Vectorised functions around candidate lists, and table functions for ranges and cells."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import PandasUDFType, pandas_udf, udtf


def galloping(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Common values of two sorted arrays, in time by the shorter one."""
    if len(a) > len(b):
        a, b = b, a
    if not len(b):
        return a
    at = np.minimum(np.searchsorted(b, a), len(b) - 1)
    return a[b[at] == a]


def _meet(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([galloping(np.asarray(x, np.int64), np.asarray(y, np.int64)) if x is not None and y is not None else None for x, y in zip(a, b)])


def intersect_sorted(a: Column | str, b: Column | str) -> Column:
    """Sorted arrays' common part: no worse than the shorter list, unlike a hashed intersection."""
    return pandas_udf(_meet, "array<long>", PandasUDFType.SCALAR)(a, b)


def rank_pair(u: Column, v: Column) -> Column:
    """An undirected edge as (smaller, larger)."""
    return F.struct(F.least(u, v).alias("lo"), F.greatest(u, v).alias("hi"))


def _net(w: pd.Series) -> int:
    return int(np.sign(w.fillna(0).sum()))


def net_sign(w: Column | str) -> Column:
    """The sign of the sum of signed changes, as a grouped aggregate."""
    return pandas_udf(_net, "long", PandasUDFType.GROUPED_AGG)(w)


@udtf(returnType="k: bigint")
class ExpandRange:
    """The numbers from start to end, for lateral joins."""

    def eval(self, start: int, end: int) -> Iterator[tuple[int]]:
        for k in range(start, end + 1):
            yield (k,)


@udtf(returnType="cell: bigint")
class HypercubeCells:
    """Cells that a row must visit: base plus every combination of the free dimensions' steps."""

    def eval(self, base: int, shares: list[int], strides: list[int]) -> Iterator[tuple[int]]:
        cells = [base]
        for share, stride in zip(shares, strides):
            cells = [c + k * stride for c in cells for k in range(share)]
        for c in cells:
            yield (c,)


def local_triangles(edges: DataFrame, key: str) -> DataFrame:
    """Triangles inside groups of edges, each group in one task: for small groups only."""

    def count(group: pa.Table) -> pa.Table:
        from motifjoin.baselines.serial import count_triangles

        n = count_triangles(group.column("src").to_numpy(), group.column("dst").to_numpy())
        return pa.table({key: group.column(key).slice(0, 1), "n": pa.array([n], pa.int64())})

    return edges.groupBy(key).applyInArrow(count, f"{key} {edges.schema[key].dataType.simpleString()}, n long")


def register(spark) -> None:
    """Make the table functions known to SQL."""
    spark.udtf.register("expand_range", ExpandRange)
    spark.udtf.register("hypercube_cells", HypercubeCells)
    spark.udf.register("intersect_sorted", pandas_udf(_meet, "array<long>", PandasUDFType.SCALAR))
