"""Exact deduplication by content-defined chunk recipes, in DataFrame operations only.

A text, with runs of white space replaced by one space, is cut after sentence ends, in chunks of bounded length.  The
cut depends on the content near it, so equal passages give equal chunks wherever they stand.  Each chunk gets a short
identifier (a 64-bit hash).  Identifiers are verified over the whole corpus: if one stands for chunks whose SHA-256
values differ, those chunks get their SHA values as identifiers instead.  A document's recipe is its ordered list of
identifiers; documents are equal if their recipes are, which the SHA-256 of their whole texts confirms.  Only recipes and
checksums move between executors, never texts.  ``chunk_table`` keeps one copy of each chunk under its identifier, and
``rebuild`` makes texts of recipes again.

Defined results: null text counts as empty, empty texts are equal to each other; of rows that share text and smallest
doc_id one is kept; null ids lose against others; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, ordered, whole

SPACE = r"[\x20\x09-\x0D]+"
#: 256 to 4096 characters up to a sentence end, else 4096 characters.
CHUNK = r"(?s).{256,4096}?(?:[.!?]\S{0,3} |$)|.{1,4096}"


def normalised(column: str = "text") -> Column:
    return F.regexp_replace(whole(column), SPACE, " ")


def recipes(docs: DataFrame, bits: int = 64) -> DataFrame:
    """doc_id, dh (hash of the text as it is), text_sha256, parts: per chunk its hash (``bits`` of it) and 60 bits of its SHA-256."""
    ids = F.transform(
        F.regexp_extract_all("norm", F.lit(CHUNK), F.lit(0)),
        lambda c: F.struct(F.shiftright(F.xxhash64(c), 64 - bits).alias("h"), F.conv(F.substring(F.sha2(c, 256), 1, 15), 16, 10).cast("long").alias("v")),
    )
    rows = docs.select("doc_id", F.xxhash64(whole()).alias("dh"), normalised().alias("norm"))
    return rows.select("doc_id", "dh", F.sha2("norm", 256).alias("text_sha256"), ids.alias("parts"))


def identified(rows: DataFrame) -> DataFrame:
    """Adds ``recipe``: the ordered verified identifiers."""
    parts = rows.select(F.explode("parts").alias("p")).select("p.h", "p.v")
    wrong = parts.groupBy("h").agg(F.min("v").alias("a"), F.max("v").alias("b")).where("a <> b").select("h", F.lit(True).alias("wrong"))
    wrong = cut(wrong, "chunk-collisions")
    plain = rows.withColumn("recipe", F.transform("parts", lambda p: F.struct(p["h"].alias("h"), F.lit(0).cast("long").alias("v"))))
    if wrong.isEmpty():
        return plain
    fixed = (
        rows.select("row", F.posexplode("parts").alias("pos", "p")).select("row", "pos", "p.h", "p.v").join(wrong, "h", "left")
        .groupBy("row").agg(F.sort_array(F.collect_set(F.struct("pos", "h", F.when(F.col("wrong"), F.col("v")).otherwise(F.lit(0)).alias("v")))).alias("list"))
        .select("row", F.transform("list", lambda x: F.struct(x["h"].alias("h"), x["v"].alias("v"))).alias("fixed"))
    )
    nothing = F.array().cast("array<struct<h:bigint,v:bigint>>")
    return rows.join(fixed, "row", "left").withColumn("recipe", F.coalesce("fixed", nothing)).drop("fixed")


def marked(docs: DataFrame, bits: int = 64) -> DataFrame:
    """One row per row of ``docs``: doc_id, dh, recipe, keep_id, group_size, kept, text_sha256."""
    # Rows are numbered and written at once, so their numbers don't change if a task is run again.
    rows = cut(recipes(docs, bits).withColumn("row", F.monotonically_increasing_id()), "chunk-recipes")
    named = identified(rows).drop("parts")
    by = ["recipe", "text_sha256"]
    # Written first, so that the join stands alone and a recipe that very many documents share can be split.
    groups = cut(named.groupBy(*by).agg(F.min(ordered("doc_id", "row")).alias("keep"), F.count(F.lit(1)).alias("group_size")), "chunk-groups")
    return named.join(groups, by).withColumn("keep_id", F.col("keep.doc_id")).withColumn("kept", F.col("row") == F.col("keep.row")).drop("keep", "row")


def exact_dedup(docs: DataFrame, bits: int = 64) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    return marked(docs, bits).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def chunk_table(docs: DataFrame) -> DataFrame:
    """h, v, chunk, uses: one copy of each distinct chunk of the normalised texts, and in how many places it stands."""
    chunks = docs.select(F.explode(F.regexp_extract_all(normalised(), F.lit(CHUNK), F.lit(0))).alias("chunk"))
    named = chunks.select(F.xxhash64("chunk").alias("h"), F.conv(F.substring(F.sha2("chunk", 256), 1, 15), 16, 10).cast("long").alias("v"), "chunk")
    return named.groupBy("h", "v").agg(F.first("chunk").alias("chunk"), F.count(F.lit(1)).alias("uses"))


def rebuild(rows: DataFrame, table: DataFrame) -> DataFrame:
    """row, norm: normalised texts from ``recipes`` rows (with a column ``row`` that tells them apart) and the chunk table."""
    placed = rows.select("row", F.posexplode_outer("parts").alias("pos", "p")).select("row", "pos", "p.h", "p.v").join(table.select("h", "v", "chunk"), ["h", "v"], "left")
    return placed.groupBy("row").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("pos", "chunk"))), lambda x: x["chunk"]), "").alias("norm"))
