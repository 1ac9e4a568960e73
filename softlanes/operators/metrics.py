"""Accuracy: squared errors, profiles over problems, ratios, exponents, agreement of rankings."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def errors(estimate: DataFrame, truth: DataFrame) -> DataFrame:
    """``(i, p, e)``; a missing row is 0 on either side."""
    return estimate.select("i", "p", "v").join(truth.select("i", "p", F.col("v").alias("t")), ["i", "p"], "full").select(
        "i", "p", (F.coalesce("v", F.lit(0.0)) - F.coalesce("t", F.lit(0.0))).alias("e")
    )


def sse(estimate: DataFrame, truth: DataFrame) -> DataFrame:
    return errors(estimate, truth).agg(F.coalesce(F.sum(F.col("e") * F.col("e")), F.lit(0.0)).alias("sse"))


def per_problem(estimate: DataFrame, truth: DataFrame) -> DataFrame:
    """``(p, sse)``: the profile whose peaks are the problems that waited for slow lanes."""
    return errors(estimate, truth).groupBy("p").agg(F.sum(F.col("e") * F.col("e")).alias("sse"))


def mse(estimate: DataFrame, truth: DataFrame, n_nodes: int) -> DataFrame:
    """Squared error in total, for each problem, and for each entry."""
    profile = per_problem(estimate, truth)
    return profile.agg(F.sum("sse").alias("sse"), F.avg("sse").alias("mse_problem"), (F.avg("sse") / n_nodes).alias("mse_entry"))


def peak_to_average(profile: DataFrame, *by: str) -> DataFrame:
    out = (profile.groupBy(*by) if by else profile.groupBy()).agg(F.max("sse").alias("peak"), F.avg("sse").alias("average"))
    return out.withColumn("ratio", F.col("peak") / F.nullif("average", F.lit(0.0)))


def ratios(scores: DataFrame, base: str, *by: str) -> DataFrame:
    """Error of every scheme over that of ``base``, side by side: ``scores(scheme, mse, *by)``."""
    schemes = [r.scheme for r in scores.select("scheme").distinct().orderBy("scheme").collect()]
    wide = scores.groupBy(*by).pivot("scheme", schemes).agg(F.avg("mse"))
    return wide.select(*by, *[(F.col(s) / F.nullif(F.col(base), F.lit(0.0))).alias(f"{s}_over_{base}") for s in schemes if s != base])


def measured_exponent(curve: DataFrame, *by: str) -> DataFrame:
    """Slope of -ln(mse) over the deadline: ``curve(deadline, mse, *by)``."""
    grouped = curve.where("mse > 0").groupBy(*by) if by else curve.where("mse > 0").groupBy()
    return grouped.agg(F.regr_slope(-F.log("mse"), F.col("deadline")).alias("exponent"))


def residual(system, state: DataFrame, forcing: DataFrame) -> DataFrame:
    """Squared residual of the fixed-point equation, for each problem."""
    return per_problem(system.step(state, forcing), state).withColumnRenamed("sse", "residual")


def top_nodes(vec: DataFrame, t: int, digits: int = 9) -> DataFrame:
    """The ``t`` largest nodes of each problem, ties by node; rounding makes ties the same in any engine."""
    w = Window.partitionBy("p").orderBy(F.desc(F.round("v", digits)), "i")
    return vec.withColumn("place", F.row_number().over(w)).where(F.col("place") <= t).select("p", "place", "i")


def top_overlap(estimate: DataFrame, truth: DataFrame, t: int) -> DataFrame:
    """Share of the true top ``t`` that the estimate's top ``t`` has, for each problem."""
    a, b = top_nodes(estimate, t).select("p", "i"), top_nodes(truth, t).select("p", "i")
    both = a.intersect(b).groupBy("p").agg(F.count("*").alias("n"))
    return truth.select("p").distinct().join(both, "p", "left").select("p", (F.coalesce("n", F.lit(0)) / t).alias("overlap"))
