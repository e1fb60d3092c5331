"""Helpers shared by the text operators: scratch tables, whole texts, partition counts."""

from __future__ import annotations

import atexit
import ctypes
import math
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import ship

BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"
_own: list[str] = []  # the folder of a local session that names none
_made: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share (``spark.checkpoint.dir``); a temporary one only where it is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="privsurv-scratch-"))
        atexit.register(shutil.rmtree, _own[0], True)
    return _own[0]


def cut(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it again: the lineage ends there and survives lost executors.

    The table stays until ``release`` is called, since lazy results may still read it.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/privsurv/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _made.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def drop(df: DataFrame) -> None:
    """Delete the scratch table that ``cut`` returned, once nothing reads it any more."""
    item = (df.sparkSession, df._scratch)
    path = item[0]._jvm.org.apache.hadoop.fs.Path(item[1])
    path.getFileSystem(item[0]._jsc.hadoopConfiguration()).delete(path, True)
    _made.remove(item)


def release(spark: SparkSession) -> None:
    """Delete the scratch tables this session wrote; results that were not written yet become unreadable."""
    jvm, hadoop = spark._jvm, spark._jsc.hadoopConfiguration()
    for item in [x for x in _made if x[0] is spark]:
        path = jvm.org.apache.hadoop.fs.Path(item[1])
        path.getFileSystem(hadoop).delete(path, True)
        _made.remove(item)


def ready(spark: SparkSession) -> SparkSession:
    """Sends the package to the executors, and keeps Arrow batches of whole texts to a few MB (a runtime setting; a session's own
    value stays)."""
    if spark.conf.get(BATCH, "10000") == "10000":
        spark.conf.set(BATCH, "1000")
    if spark.conf.get(BATCH_BYTES, "64m") in ("67108864b", "64m"):
        spark.conf.set(BATCH_BYTES, "8m")
    return ship(spark)


@cache
def _libc():
    """The C library, told to hand arrays above a megabyte back to the system when they are freed; None where it isn't glibc."""
    try:
        libc = ctypes.CDLL("libc.so.6")
        libc.mallopt(-3, 1 << 20)  # M_MMAP_THRESHOLD, which would grow otherwise
        libc.mallopt(-1, 1 << 24)  # M_TRIM_THRESHOLD
        return libc
    except (OSError, AttributeError):
        return None


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """``run`` for a Python worker that gives freed memory back, since workers live on between tasks and stages."""

    def wrapped(frames: Iterator) -> Iterator:
        libc = _libc()
        yield from run(frames)
        if libc is not None:
            libc.malloc_trim(0)

    return wrapped


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    ready(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def whole(column: str = "text") -> Column:
    """The text, null read as empty."""
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def unused(df: DataFrame, name: str) -> str:
    """``name`` with underscores in front until no column of ``df`` has it."""
    held = {c.lower() for c in df.columns}
    while name.lower() in held:
        name = "_" + name
    return name


def ordered(*names: str) -> Column:
    """Struct to take minima of: ids first, nulls after all others."""
    return F.struct(F.col(names[0]).isNull().alias("none"), *[F.col(n).alias(n) for n in names])


def one_each(docs: DataFrame, kept: DataFrame) -> DataFrame:
    """The rows of ``docs`` that ``kept`` names by doc_id and dh (a hash of the whole text), one row for each.

    Rows that repeat both are the same document; one of them stays.  They are looked for in a narrow table, and only they go
    through a grouping.
    """
    dh, i, h = (unused(docs, n) for n in ("__dh", "__id", "__hash"))
    named = docs.withColumn(dh, F.xxhash64(whole()))
    kept = kept.select(F.col("doc_id").alias(i), F.col("dh").alias(h))
    twins = cut(named.groupBy("doc_id", dh).agg(F.count(F.lit(1)).alias("rows")).where("rows > 1").select(F.col("doc_id").alias(i), F.col(dh).alias(h)), "twins")
    same = lambda few: named["doc_id"].eqNullSafe(few[i]) & (named[dh] == few[h])
    if twins.isEmpty():
        return named.join(kept, same(kept), "left_semi").drop(dh)
    single = kept.join(twins, kept[i].eqNullSafe(twins[i]) & (kept[h] == twins[h]), "left_anti")
    double = kept.join(twins, kept[i].eqNullSafe(twins[i]) & (kept[h] == twins[h]), "left_semi")
    repeated = named.join(double, same(double), "left_semi").dropDuplicates(["doc_id", dh])
    return named.join(single, same(single), "left_semi").unionByName(repeated).drop(dh)


def sample_texts(docs: DataFrame, picked: list[tuple[int, object]], kind: str, most_chars: int) -> list[tuple[int, str, object]]:
    """Whole texts of the picked ids with their values, by id: as many as fit ``most_chars`` in the order given.

    ``picked`` has a stated bound; with ``most_chars`` what is collected is bounded in bytes too.  Of rows that share an id the
    least text counts.
    """
    spark = docs.sparkSession
    few = spark.createDataFrame([(i, v, k) for k, (i, v) in enumerate(picked)], f"__id long, __value {kind}, __place int")
    rows = docs.select("doc_id", "text").join(F.broadcast(few), F.col("doc_id") == F.col("__id")).where("text is not null")
    rows = cut(rows.groupBy("__id", "__value", "__place").agg(F.min("text").alias("text")), "sample")
    room, chosen = most_chars, []
    for r in rows.select("__place", F.length("text").alias("n")).orderBy("__place").collect():  # one row per picked id
        if r["n"] <= room:
            chosen.append(r["__place"])
            room -= r["n"]
    kept = spark.createDataFrame([(k,) for k in chosen], "__place int")
    return [(r[0], r[1], r[2]) for r in rows.join(F.broadcast(kept), "__place").select("__id", "text", "__value").orderBy("__id").collect()]


def parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def cells(rows: int, each: int, most: int = 1 << 16) -> int:
    """How many cells of about ``each`` rows hold ``rows`` rows; bounded, since cell counts reach the driver."""
    return int(min(most, max(1, math.ceil(rows / each))))
