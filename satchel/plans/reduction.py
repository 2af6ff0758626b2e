"""The other way round: any integer linear program as a package query over a relation made for it."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..functions.build import package_of, sum_
from ..lang.ast import And, PackageQuery


def ilp_to_package(spark: SparkSession, cost: np.ndarray, B: np.ndarray, bounds: np.ndarray) -> tuple[DataFrame, PackageQuery]:
    """max cost @ x with B x <= bounds, x whole and not negative: a tuple per variable, an attribute per row, unlimited repetition."""
    names = [f"attr_{i + 1}" for i in range(len(B))]
    rows = [(j, float(cost[j]), *(float(B[i][j]) for i in range(len(B)))) for j in range(len(cost))]
    df = spark.createDataFrame(rows, "tid long, attr_obj double, " + ", ".join(f"{n} double" for n in names))
    conditions = tuple(sum_(n) <= float(b) for n, b in zip(names, bounds, strict=True))
    q = package_of(df).repeat(None).such_that(And(conditions)).maximize(sum_("attr_obj")).query
    return df, q
