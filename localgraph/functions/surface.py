"""SQL-callable functions: pandas UDFs over curves and cuts, and table functions over masks and scales."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ..graph import Graph


@pandas_udf(T.DoubleType())
def slope_at(ratios: pd.Series, volumes: pd.Series, x: pd.Series) -> pd.Series:
    """Ratio of the first prefix that reaches x, 0 past the support."""
    return pd.Series([next((r for r, v in zip(rs, vs, strict=True) if v >= at), 0.0) for rs, vs, at in zip(ratios, volumes, x, strict=True)])


@pandas_udf(T.DoubleType())
def conductance(cut: pd.Series, vol: pd.Series, total: pd.Series) -> float:
    """Conductance of a set from the rows of its members: cut arcs, degrees, graph volume."""
    side = min(vol.sum(), total.iloc[0] - vol.sum())
    return float(cut.sum() / side) if side > 0 else float("nan")


@udtf(returnType=T.StructType().add("mask", T.LongType()).add("size", T.IntegerType()))
class SubsetMasks:
    """All proper subsets of n elements up to complement."""

    def eval(self, n: int):
        for m in range(1, 1 << max(0, n - 1)):
            yield m, m.bit_count()


@udtf(returnType=T.StructType().add("b", T.IntegerType()).add("p", T.DoubleType()))
class GeometricScales:
    """Scales 1..ell with their probabilities."""

    def eval(self, ell: int):
        for i in range(1, ell + 1):
            yield i, 2.0**-i / (1 - 2.0**-ell)


def register(spark: SparkSession, g: Graph | None = None) -> None:
    """Register the functions and, for a graph, the views arcs and vertices."""
    spark.udf.register("slope_at", slope_at)
    spark.udf.register("conductance", conductance)
    spark.udtf.register("subset_masks", SubsetMasks)
    spark.udtf.register("geometric_scales", GeometricScales)
    if g is not None:
        g.arcs.createOrReplaceTempView("arcs")
        g.vertices.createOrReplaceTempView("vertices")


def member_rows(g: Graph, sets):
    """(set_id, cut, vol, total) per member, the input of `conductance`."""
    out = sets.join(g.arcs, sets["v"] == g.arcs["src"]).select("set_id", sets["v"].alias("v"), "dst")
    gone = out.join(sets.select("set_id", F.col("v").alias("dst")), ["set_id", "dst"], "left_anti").groupBy("set_id", "v").agg(F.count("*").alias("cut"))
    return sets.join(gone, ["set_id", "v"], "left").join(g.vertices, "v").select("set_id", F.coalesce("cut", F.lit(0)).alias("cut"), F.col("deg").alias("vol"), F.lit(g.vol).alias("total"))
