"""Accuracy measures of estimates and their summaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

QUANTILES = (0.05, 0.25, 0.5, 0.75, 0.95)


def q_error(truth: Column, estimate: Column, floor: float | Column = 1.0) -> Column:
    """The larger of the two ratios; both sides are lifted to ``floor`` (one tuple)."""
    f = floor if isinstance(floor, Column) else F.lit(float(floor))
    t, e = F.greatest(truth.cast("double"), f), F.greatest(estimate.cast("double"), f)
    return F.greatest(t / e, e / t)


def log_q_error(truth: Column, estimate: Column, floor: float | Column = 1.0) -> Column:
    return F.log10(q_error(truth, estimate, floor))


def relative_error(truth: Column, estimate: Column, floor: float = 1.0) -> Column:
    """Asymmetric: an estimate of zero never costs more than one. Kept for contrast."""
    return F.abs(estimate - truth) / F.greatest(truth.cast("double"), F.lit(float(floor)))


def box_plot(errors: DataFrame, by: list[str], column: str = "qerr", exact: bool = True) -> DataFrame:
    """One row a group: count, the five quantiles, mean and maximum. ``exact=False`` uses a sketch."""
    q = F.percentile(column, F.array(*map(F.lit, QUANTILES))) if exact else F.percentile_approx(column, list(QUANTILES), 10_000)
    boxed = errors.groupBy(*by).agg(F.count("*").alias("n"), q.alias("q"), F.avg(column).alias("mean"), F.max(column).alias("max"))
    return boxed.select(*by, "n", *(F.col("q")[k].alias(f"p{int(100 * x):02d}") for k, x in enumerate(QUANTILES)), "mean", "max")


def error_summary(errors: DataFrame, by: list[str], column: str = "qerr") -> DataFrame:
    return errors.groupBy(*by).agg(F.count("*").alias("n"), F.avg(column).alias("mean"), F.max(column).alias("worst"))


def selectivity_bucket(selectivity: Column) -> Column:
    return F.when(selectivity >= 0.05, "1: 5% or more").when(selectivity >= 0.01, "2: 1% to 5%").when(selectivity >= 0.001, "3: 0.1% to 1%").otherwise("4: under 0.1%")
