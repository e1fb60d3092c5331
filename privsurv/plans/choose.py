"""Physical choices that the engine makes in the open: how to evaluate the data term, and how to feed chains."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.chain import POOL


@dataclass(frozen=True)
class Choice:
    name: str
    why: str

    def explain(self) -> str:
        return f"{self.name}: {self.why}"


def evaluator(df: DataFrame, x: list[str], q: int, tolerance: float = 0.0) -> Choice:
    """``cells`` if compression pays by a factor of ten, ``table`` if an error is allowed and q is large, else the Arrow ``kernel``;
    ``columns`` for a handful of intervals.  One aggregate with sketches decides."""
    row = df.agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct(F.xxhash64("t", "y", *x)).alias("cells")).first()
    if row["cells"] * 10 <= row["n"]:
        return Choice("cells", f"{row['n']} records have about {row['cells']} distinct cells")
    if q <= 8:
        return Choice("columns", f"{q} intervals unroll into one expression")
    if tolerance > 0 and q >= 50:
        return Choice("table", f"an error of {tolerance:g} is allowed, and {q} terms become one lookup")
    return Choice("kernel", f"{row['n']} records of up to {q} terms each")


def feeding(n: float, p: int, steps: int, k: int) -> Choice:
    """Whether chains get the whole pool by broadcast or their minibatches by joins."""
    if n * (2 + p) <= POOL:
        return Choice("broadcast", f"{n:.0f} records of {p} covariates are below {POOL} numbers")
    return Choice("prefetch", f"{steps * k * (p + 2) * 8 / 1e6:.0f} MB of minibatch rows move instead of {n * (p + 2) * 8 / 1e6:.0f} MB of records per executor")
