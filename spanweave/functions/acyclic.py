"""Aggregates over edge sets."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql.functions import pandas_udf
from pyspark.sql.pandas.functions import PandasUDFType

from ..kernels.graph import UnionFind


def _acyclic(src: pd.Series, dst: pd.Series) -> bool:
    names = {v: k for k, v in enumerate(pd.unique(pd.concat([src, dst])))}
    joined = UnionFind(len(names))
    return all(joined.union(names[a], names[b]) for a, b in zip(src, dst, strict=True))


def is_acyclic(src: str, dst: str) -> Column:
    """Aggregate: whether a group's edges (one row each; repeated rows are parallel edges) have no cycle."""
    return pandas_udf(_acyclic, "boolean", PandasUDFType.GROUPED_AGG)(src, dst)
