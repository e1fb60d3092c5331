"""Accuracy, convergence and quality measures over traces, curves of results, and scored records."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _array(v: Sequence[float]) -> Column:
    return F.array(*[F.lit(float(x)) for x in v])


def distance(f: Column, star: Column) -> Column:
    """Relative Euclidean distance of two arrays."""
    square = lambda c: F.aggregate(c, F.lit(0.0), lambda acc, v: acc + v * v)
    return F.sqrt(square(F.zip_with(f, star, lambda a, b: a - b)) / square(star))


def mre(draws: DataFrame, star: Sequence[float], by: Sequence[str] = ()) -> DataFrame:
    """Mean relative error of draws (column f) from the reference vector."""
    return draws.groupBy(*by).agg(F.avg(distance(F.col("f"), _array(star))).alias("mre"), F.count(F.lit(1)).alias("draws"))


def relative_error(a: Column, b: Column) -> Column:
    return distance(a, b)


def running_mre(trace: DataFrame, star: Sequence[float], epoch: int) -> DataFrame:
    """chain_id, epoch, mre over all states up to the end of the epoch."""
    per = trace.withColumn("epoch", F.ceil(F.col("step") / epoch).cast("long")).withColumn("__d", distance(F.col("f"), _array(star))).groupBy("chain_id", "epoch").agg(F.sum("__d").alias("s"), F.count(F.lit(1)).alias("n"))
    up = Window.partitionBy("chain_id").orderBy("epoch").rowsBetween(Window.unboundedPreceding, 0)
    return per.select("chain_id", "epoch", (F.sum("s").over(up) / F.sum("n").over(up)).alias("mre"))


def density(trace: DataFrame, index: int, low: float, high: float, bins: int) -> DataFrame:
    """Histogram density of one coefficient."""
    b = F.width_bucket(F.get("f", index), F.lit(low), F.lit(high), F.lit(bins))
    all_ = Window.partitionBy(F.lit(0))
    counts = trace.groupBy(b.alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    return counts.select("bin", "n", (F.col("n") / F.sum("n").over(all_) / ((high - low) / bins)).alias("density"))


def densities(trace: DataFrame, indices: Sequence[int], low: float, high: float, bins: int) -> DataFrame:
    """``density`` of several coefficients (component counts from one) in one pass over the trace, which may cost a chain's run."""
    each = F.explode(F.array(*[F.struct(F.lit(k + 1).alias("component"), F.get("f", i).alias("v")) for k, i in enumerate(indices)])).alias("c")
    counts = trace.select(each).select("c.component", F.width_bucket("c.v", F.lit(low), F.lit(high), F.lit(bins)).alias("bin")).groupBy("component", "bin").agg(F.count(F.lit(1)).alias("n"))
    all_ = F.sum("n").over(Window.partitionBy("component"))
    return counts.select("component", "bin", "n", (F.col("n") / all_ / ((high - low) / bins)).alias("density"))


def kernel_density(trace: DataFrame, index: int, points: Sequence[float], width: float) -> DataFrame:
    """Normal-kernel density of one coefficient at the given points; partial sums per point are made before the shuffle."""
    at = F.explode(F.array(*[F.lit(float(p)) for p in points])).alias("point")
    z = (F.col("point") - F.col("v")) / width
    own = trace.select(F.get("f", index).alias("v"), at)
    return own.groupBy("point").agg(F.avg(F.exp(-0.5 * z * z) / (width * math.sqrt(2 * math.pi))).alias("density"))


def moments(trace: DataFrame, index: int, by: Sequence[str] = ()) -> DataFrame:
    """Mean, spread, skewness and kurtosis: near a normal law the last two are near zero."""
    v = F.get("f", index)
    return trace.groupBy(*by).agg(F.avg(v).alias("mean"), F.stddev_pop(v).alias("sd"), F.skewness(v).alias("skewness"), F.kurtosis(v).alias("kurtosis"))


def rhat(trace: DataFrame, index: int) -> DataFrame:
    """Split-chain potential scale reduction of one coefficient, and a lag-one effective size."""
    v = trace.select("chain_id", "step", F.get("f", index).alias("v"))
    half = F.ntile(2).over(Window.partitionBy("chain_id").orderBy("step"))
    v = v.withColumn("half", half).withColumn("before", F.lag("v").over(Window.partitionBy("chain_id").orderBy("step")))
    own = v.groupBy("chain_id", "half").agg(F.avg("v").alias("m"), F.var_samp("v").alias("s2"), F.count(F.lit(1)).alias("n"), F.corr("v", "before").alias("r"))
    out = own.agg(F.avg("s2").alias("within"), F.var_samp("m").alias("between"), F.avg("n").alias("n"), F.avg("r").alias("r"), F.sum("n").alias("all"))
    return out.select(F.sqrt((F.col("n") - 1) / F.col("n") + F.col("between") / F.col("within")).alias("rhat"), (F.col("all") * (1 - F.col("r")) / (1 + F.col("r"))).alias("effective"))


def converged(curve: DataFrame, last: int, tolerance: float) -> DataFrame:
    """Whether the slope of the running error over the last epochs is below the tolerance per epoch."""
    own = curve.withColumn("top", F.max("epoch").over(Window.partitionBy("chain_id"))).where(F.col("epoch") > F.col("top") - last)
    return own.groupBy("chain_id").agg(F.regr_slope("mre", "epoch").alias("slope")).withColumn("stable", F.abs("slope") <= tolerance)


def best_lambda(curve: DataFrame) -> DataFrame:
    w = Window.partitionBy("dataset").orderBy("value", "lambda")
    return curve.withColumn("k", F.row_number().over(w)).where("k = 1").select("dataset", "lambda", "value")


def rank_methods(curve: DataFrame) -> DataFrame:
    return curve.withColumn("rank", F.rank().over(Window.partitionBy("dataset", "epsilon").orderBy("value")))


def fit_quality(records: DataFrame, loss: Column, d: int) -> DataFrame:
    """Log-likelihood, deviance and AIC."""
    row = records.agg((-F.sum(F.col("w") * loss)).alias("loglik"))
    return row.select("loglik", (-2 * F.col("loglik")).alias("deviance"), (2 * d - 2 * F.col("loglik")).alias("aic"))


def brier(records: DataFrame, survival: Column, at: int) -> DataFrame:
    """Mean squared error of predicted survival past ``at`` among records known by then."""
    known = (F.col("t") > at) | (F.col("y") == 1)
    alive = (F.col("t") > at).cast("double")
    return records.where(known).agg(F.avg((alive - survival) ** 2).alias("brier"), F.count(F.lit(1)).alias("n"))


def concordance(records: DataFrame, score: str = "z", bins: int = 1000) -> DataFrame:
    """Share of usable pairs (earlier event, later end) whose scores agree, from counts per interval and score bin.

    Scores are binned at ``bins`` equal-width steps, ties count one half; the counts (at most q times bins rows) are all that is joined.
    """
    range_ = records.agg(F.min(score).alias("lo"), F.max(score).alias("hi"))
    b = F.least(F.lit(bins - 1), F.floor((F.col(score) - F.col("lo")) / F.greatest(F.col("hi") - F.col("lo"), F.lit(1e-12)) * bins)).cast("int")
    cells = records.crossJoin(F.broadcast(range_)).groupBy("t", b.alias("b")).agg(F.sum("w").alias("n"), F.sum(F.when(F.col("y") == 1, F.col("w")).otherwise(0)).alias("m"))
    late = cells.select(F.col("t").alias("t2"), F.col("b").alias("b2"), F.col("n").alias("n2"))
    pairs = cells.where("m > 0").join(F.broadcast(late), F.col("t2") > F.col("t"))
    agree = F.when(F.col("b") > F.col("b2"), 1.0).when(F.col("b") == F.col("b2"), 0.5).otherwise(0.0)
    n = F.col("m") * F.col("n2")
    return pairs.agg((F.sum(n * agree) / F.sum(n)).alias("concordance"), F.sum(n).cast("long").alias("pairs"))
