"""Planted survival data with known coefficients, as a generator of columns and as a Python data source."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions import basis, links, loss, rng

ALPHA, BETA = "-4,1,-1", "0.8,-0.5,0.3"


def planted(spark: SparkSession, n: int, alpha: Sequence[float], beta: Sequence[float], q: int, seed: int = 1, censor: float = 1.0) -> DataFrame:
    """subject_id, unit_id, t, y, x1..xp, w.  Covariates are uniform in a cube inside the unit ball; the event time has the model's
    hazards; censoring is uniform over the intervals with probability ``censor``, else at q."""
    p = len(beta)
    side = 1 / p**0.5
    df = spark.range(n).select(F.col("id").alias("subject_id"), *[((2 * rng.uniform(str(seed), f"x{j}", F.col("id")) - 1) * side).alias(f"x{j + 1}") for j in range(p)])
    z = loss.dot([F.col(f"x{j + 1}") for j in range(p)], beta)
    df = df.withColumn("__z", z).withColumn("__u", -F.log(rng.uniform(str(seed), "event", F.col("subject_id"))))
    # First s at which the cumulative hazard passes an exponential threshold.
    state = F.aggregate(
        F.sequence(F.lit(1), F.lit(q)), F.struct(F.lit(0.0).alias("h"), F.lit(0).alias("t")),
        lambda a, s: F.struct((a["h"] + links.softplus(loss.baseline(s, alpha, q) + F.col("__z"))).alias("h"), F.when((a["t"] == 0) & (a["h"] + links.softplus(loss.baseline(s, alpha, q) + F.col("__z")) >= F.col("__u")), s).otherwise(a["t"]).alias("t")))
    df = df.withColumn("__t", state["t"])
    cut = F.when(rng.uniform(str(seed), "whether", F.col("subject_id")) < censor, F.ceil(rng.uniform(str(seed), "censor", F.col("subject_id")) * q)).otherwise(q).cast("int")
    df = df.withColumn("__c", cut).withColumn("__e", (F.col("__t") > 0) & (F.col("__t") <= F.col("__c")))
    return df.select("subject_id", F.col("subject_id").alias("unit_id"), F.when(F.col("__e"), F.col("__t")).otherwise(F.col("__c")).alias("t"), F.when(F.col("__e"), 1).otherwise(-1).alias("y"), *[f"x{j + 1}" for j in range(p)], F.lit(1).cast("long").alias("w"))


class _Range(InputPartition):
    def __init__(self, begin: int, end: int):
        self.begin, self.end = begin, end


def _numbers(text: str) -> list[float]:
    return [float(v) for v in text.split(",")]


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.n, self.q, self.seed = int(options.get("n", 1000)), int(options.get("q", 20)), options.get("seed", "1")
        self.alpha, self.beta = _numbers(options.get("alpha", ALPHA)), _numbers(options.get("beta", BETA))
        self.parts, self.censor = int(options.get("partitions", 4)), float(options.get("censor", 1.0))

    def partitions(self) -> Sequence[InputPartition]:
        step = max(1, -(-self.n // self.parts))
        return [_Range(a, min(a + step, self.n)) for a in range(0, self.n, step)]

    def read(self, partition: _Range):
        gamma, side = basis.matrix(self.q, len(self.alpha)) @ np.array(self.alpha), 1 / len(self.beta) ** 0.5
        for i in range(partition.begin, partition.end):
            x = [(2 * rng.value(self.seed, f"x{j}", i) - 1) * side for j in range(len(self.beta))]
            passed = np.cumsum(np.logaddexp(0, gamma + float(np.dot(x, self.beta)))) >= -math.log(rng.value(self.seed, "event", i))
            t = int(passed.argmax()) + 1 if passed.any() else self.q + 1
            cut = math.ceil(rng.value(self.seed, "censor", i) * self.q) if rng.value(self.seed, "whether", i) < self.censor else self.q
            yield (i, min(t, cut), 1 if t <= cut else -1, *x)


class PlantedSource(DataSource):
    """``spark.read.format("planted_survival")``: the records of ``planted``, made in Python.  Options n, q, seed, censor, partitions, and
    alpha and beta (numbers with commas between)."""

    @classmethod
    def name(cls) -> str:
        return "planted_survival"

    def schema(self) -> str:
        return "subject_id long, t int, y int, " + ", ".join(f"x{j + 1} double" for j in range(len(_numbers(self.options.get("beta", BETA)))))

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedSource)
