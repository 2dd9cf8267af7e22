"""Functions for SQL users: a table function of triangle routing, and an aggregate that keeps minimal masks."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from depmine.functions.bits import antichain


class TriangleCells:
    """triangle_cells(anchor, side): the cells x <= y of the triangle grid that touch an anchor, and on which side a row with it stands there."""

    def eval(self, anchor: int, side: int):
        if anchor is not None and side is not None:
            for other in range(side):
                x, y = min(anchor, other), max(anchor, other)
                yield x * side + y, anchor == x, anchor == y


def _minimal_masks(masks: pd.Series) -> list[int]:
    return antichain(int(m) for m in masks.dropna())


def register(spark: SparkSession) -> None:
    """Make triangle_cells(anchor, side) and mask_antichain(mask) known to SQL."""
    from pyspark.sql.functions import pandas_udf, udtf

    spark.udtf.register("triangle_cells", udtf(TriangleCells, returnType="cell int, stands_left boolean, stands_right boolean"))
    spark.udf.register("mask_antichain", mask_antichain(pandas_udf))


def mask_antichain(pandas_udf=F.pandas_udf):
    """Grouped aggregate over a column of masks (long): those that contain no other one. Reduce partitions of a large group first: the result of parts may be aggregated again."""

    def run(masks: pd.Series) -> list[int]:
        return _minimal_masks(masks)

    run.__annotations__ = {"masks": pd.Series, "return": list}
    return pandas_udf(run, "array<long>", F.PandasUDFType.GROUPED_AGG)
