"""Uniform shuffle of documents into shards of exact sizes (law ``rows``).

Rows are dealt to source cells by a hash.  One matrix says how many rows each cell sends to each shard; it is drawn
from the law a uniform random permutation has (multivariate hypergeometric, with the shard sizes as margins), so shard
sizes are exact before any row moves.  Each cell permutes its rows by a seeded hash and deals them out by its row of
the matrix; after the exchange each shard is permuted again, in blocks with known offsets, which gives gapless slots.

Only the cell counts (at most 65,536) and the drawn matrix are on the driver.  All row work is DataFrame operations.

Defined results: null text counts as empty (size 16, checksum 0); null ids are ordinary keys; repeated rows are placed
once each; an empty table gives no rows; extra columns are ignored by ``shard`` and never clash.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cells, cut

OVERHEAD = 16  # bytes a stored row has besides its text


def draw(rng: np.random.Generator, good: int, bad: int, n: int) -> int:
    """Successes among ``n`` draws without replacement; above the generator's limit by ratio of uniforms."""
    if n <= 0 or good <= 0:
        return 0
    if bad <= 0:
        return n
    if good + bad < 1_000_000_000:
        return int(rng.hypergeometric(good, bad, n))
    total = good + bad
    p = good / total
    spread = math.sqrt(n * p * (1 - p) * max(total - n, 0) / (total - 1) + 0.5)
    low, high = max(0, n - bad), min(n, good)
    lg = math.lgamma

    def weight(k: int) -> float:
        return -(lg(k + 1) + lg(good - k + 1) + lg(n - k + 1) + lg(bad - n + k + 1))

    mode = min(high, max(low, (n + 1) * (good + 1) // (total + 2)))
    top, wide = weight(mode), 1.7156 * spread + 0.8989  # fixed constants of the ratio-of-uniforms hat
    while True:
        u, v = rng.random(), rng.random()
        if u == 0:
            continue
        k = math.floor(n * p + 0.5 + wide * (v - 0.5) / u)
        if low <= k <= high and 2 * math.log(u) <= weight(k) - top:
            return k


def matrix(counts: list[int], sizes: list[int], seed: int) -> np.ndarray:
    """Rows to send from each cell to each shard: margins ``counts`` and ``sizes`` hold exactly."""
    rng, left = np.random.default_rng(seed), list(sizes)
    out = np.zeros((len(counts), len(sizes)), dtype=np.int64)
    for i, n in enumerate(counts):
        rest = sum(left)
        for j in range(len(left)):
            rest -= left[j]
            out[i, j] = k = draw(rng, left[j], rest, n)
            left[j] -= k
            n -= k
    return out


def _hash(seed: int, *names: str) -> Column:
    return F.xxhash64(F.lit(seed), *[F.col(x) for x in names])


def shard(docs: DataFrame, shards: int = 40, seed: int = 20, cell_rows: int = 20_000) -> DataFrame:
    """One row per document: doc_id, size, text_crc32, law, shard, slot, grown_shard (null under this law)."""
    spark = docs.sparkSession
    raw = F.encode(F.coalesce(F.col("text").cast("string"), F.lit("")), "UTF-8")
    base = cut(docs.select("doc_id", (F.octet_length(raw) + OVERHEAD).cast("long").alias("size"), F.crc32(raw).alias("text_crc32")), "shard-rows")
    rows = base.count()
    many = cells(rows, cell_rows)
    dealt = base.withColumn("h", _hash(seed, "doc_id", "text_crc32", "size")).withColumn("cell", F.pmod("h", F.lit(many)).cast("int"))
    counted = {r[0]: r[1] for r in dealt.groupBy("cell").count().collect()}  # at most 65,536 rows
    sizes = [rows // shards + (j < rows % shards) for j in range(shards)]
    ends = matrix([counted.get(i, 0) for i in range(many)], sizes, seed).cumsum(axis=1)
    plan = spark.createDataFrame([(i, [int(x) for x in r]) for i, r in enumerate(ends)], "cell int, ends array<bigint>")
    local = Window.partitionBy("cell").orderBy(_hash(seed + 1, "h"), "doc_id", "text_crc32")
    moved = (
        dealt.withColumn("at", F.row_number().over(local).cast("long") - 1)
        .join(F.broadcast(plan), "cell")  # at most 65,536 rows of one number per shard
        .withColumn("shard", F.expr("size(filter(ends, x -> x <= at))").cast("int"))
    )
    blocks = max(1, many // max(1, shards))
    moved = cut(moved.select("doc_id", "size", "text_crc32", "h", "shard", F.pmod(_hash(seed + 2, "h"), F.lit(blocks)).cast("int").alias("block")), "shard-moved")
    before = Window.partitionBy("shard").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    first = moved.groupBy("shard", "block").count().select("shard", "block", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first"))
    again = Window.partitionBy("shard", "block").orderBy(_hash(seed + 3, "h"), "doc_id", "text_crc32")
    return (
        moved.withColumn("nth", F.row_number().over(again).cast("long") - 1)
        .join(F.broadcast(first), ["shard", "block"])  # as many rows as cells at most
        .select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", (F.col("first") + F.col("nth")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
    )
