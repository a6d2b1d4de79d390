"""User-defined functions: scalar, vectorised, aggregate, table, co-grouped, and SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.exchange import Owned, common_entries, messages


@F.pandas_udf(T.LongType())
def common(a: pd.Series, b: pd.Series) -> pd.Series:
    """Sizes of the intersections of two columns of sorted lists."""
    return pd.Series([len(np.intersect1d(x, y, assume_unique=True)) for x, y in zip(a, b, strict=True)], dtype="int64")


@F.arrow_udf(T.LongType())
def list_sizes(a: pa.Array) -> pa.Array:
    """Lengths of lists, straight on the Arrow column."""
    import pyarrow.compute as pc

    return pc.cast(pc.fill_null(pc.list_value_length(a), 0), pa.int64())


@F.pandas_udf(T.DoubleType())
def gini(loads: pd.Series) -> float:
    """Gini coefficient of the loads of a group."""
    x = np.sort(loads.to_numpy(dtype=float))
    n = len(x)
    return float((2 * np.arange(1, n + 1) - n - 1) @ x / (n * x.sum())) if n and x.sum() else 0.0


@F.udtf(returnType=T.StructType([T.StructField(x, T.LongType()) for x in "abc"]))
class TrianglesOf:
    """The triangles of one list of edges, given as an array of structs (src, dst); for lists that fit a row."""

    def eval(self, edges: list) -> Iterator[tuple[int, int, int]]:
        near: dict[int, set[int]] = {}
        for e in edges or []:
            if e["src"] != e["dst"]:
                near.setdefault(min(e["src"], e["dst"]), set()).add(max(e["src"], e["dst"]))
        for a in sorted(near):
            for b in sorted(near[a]):
                for c in sorted(near[a] & near.get(b, set())):
                    yield a, b, c


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    spark.udtf.register("triangles_of", TrianglesOf)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION order_before(d1 BIGINT, i1 BIGINT, d2 BIGINT, i2 BIGINT) RETURNS BOOLEAN RETURN d1 < d2 OR (d1 = d2 AND i1 < i2)")


def receive_cogrouped(owned: Owned) -> DataFrame:
    """The surrogate receiver as a co-grouped function: messages and owned lists of a block meet in one call, as arrays."""
    sent = messages(owned).select(F.col("dest").alias("part"), "nbrs")
    own = owned.nodes.where("eff > 0").select("part", "id", "nbrs")

    def lists(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
        c = column.combine_chunks()
        c = c.chunk(0) if isinstance(c, pa.ChunkedArray) else c
        off = c.offsets.to_numpy().astype(np.int64)
        return off - off[0], c.values.to_numpy(zero_copy_only=False)[off[0] : off[-1]]

    def block(left: pa.Table, right: pa.Table) -> pa.Table:
        part = (left if left.num_rows else right).column("part")[0].as_py()
        total = 0
        if left.num_rows and right.num_rows:
            right = right.sort_by("id")
            total = common_entries(right.column("id").to_numpy(), *lists(right.column("nbrs")), *lists(left.column("nbrs")))
        return pa.table({"part": pa.array([part], pa.int32()), "triangles": pa.array([total], pa.int64())})

    return sent.groupBy("part").cogroup(own.groupBy("part")).applyInArrow(block, "part int, triangles long")
