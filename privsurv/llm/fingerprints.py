"""MinHash fingerprints of whole documents, and near copies by bands of them.

A fingerprint has sixteen bits of each of 128 minima of universal hash functions over word shingles, computed in numpy; it is
printed in hexadecimal digits, four for a minimum.  The likeness of two fingerprints is the share of equal positions (two different
minima agree by chance once in 65,536); equal texts have likeness one.  ``near_copies`` joins bands of four positions in Spark and verifies Jaccard exactly.

``with_edits`` compares each document with an edited text (its end replaced by the beginning of the next document in id
order) and with the next document.  Documents are dealt by ranges of ids, whose bounds are ids of the table; the first
document of a range is also sent to the range before, so each text moves once and no task sees more than its range.

Defined results: null texts count as empty; all texts without words but with the same characters are equal; null ids
come first; rows that repeat an id follow each other in order of their texts' hashes; a single document is its own next one.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import links
from . import shingles as S
from .common import cells, lean, parts, whole

COUNT = 128
BANDS = 32
SEED = 11


def signatures(texts: list[str], count: int = COUNT) -> np.ndarray:
    out = []
    for a, b in S.batches([len(t) for t in texts]):
        out.append(S.minhash(*S.shingles(texts[a:b]), count, SEED))
    return np.concatenate(out) if out else np.zeros((0, count), np.uint32)


def kept_bits(sig: np.ndarray) -> np.ndarray:
    """Fingerprints of full minima."""
    return (sig & 0xFFFF).astype(">u2")


def printed(prints: np.ndarray) -> list[str]:
    return [r.tobytes().hex() for r in prints]


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Of two arrays of fingerprints, row by row."""
    return (a == b).mean(axis=1)


def edited(text: str, after: str) -> str:
    cut_ = len(text) // 4
    return text[: len(text) - cut_] + after[:cut_]


def _ranges(docs: DataFrame, rows_each: int) -> list[int]:
    """Ids of the table that begin its ranges; the first is the smallest."""
    many = cells(docs.count(), rows_each, 4096)
    found = docs.where("doc_id is not null").approxQuantile("doc_id", [i / many for i in range(many)], 0.2 / many) if many > 1 else []
    least = docs.agg(F.min("doc_id")).first()[0]
    return [] if least is None else sorted({int(least), *map(int, found)})


def with_edits(docs: DataFrame, rows_each: int = 2_000) -> DataFrame:
    """One row per document: doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole().alias("text"))
    bounds = _ranges(docs.select("doc_id"), rows_each)
    nulls = docs.where("doc_id is null").isEmpty()
    array = F.array(*[F.lit(x) for x in bounds]) if bounds else F.array(F.lit(0).cast("long"))
    # The range of an id: binary search over the bounds.
    steps = [1 << k for k in range(len(bounds).bit_length(), -1, -1)]
    place = F.lit(0)
    held = docs.withColumn("bounds", array)
    place = F.aggregate(F.array(*[F.lit(s) for s in steps]), F.lit(0), lambda at, s: F.when((at + s < len(bounds)) & (F.get("bounds", at + s) <= F.col("doc_id")), at + s).otherwise(at))
    held = held.withColumn("place", F.coalesce(place, F.lit(0))).withColumn("opens", F.array_contains("bounds", F.col("doc_id")) if nulls else F.coalesce(F.array_contains("bounds", F.col("doc_id")), F.lit(True)))
    last = max(0, len(bounds) - 1)
    if nulls:
        head = F.col("opens")
        before = F.when(F.col("place") == 0, last).otherwise(F.col("place") - 1)
    else:  # rows without id come first of all: they, not the smallest id, follow the last document
        head = F.col("doc_id").isNull() | (F.col("opens") & (F.col("place") > 0))
        before = F.when(F.col("doc_id").isNull(), last).otherwise(F.col("place") - 1)
    sent = held.select("doc_id", "text", F.explode(F.when(head, F.array(F.struct(F.col("place").alias("range"), F.lit(0).alias("guest")), F.struct(before.alias("range"), F.lit(1).alias("guest")))).otherwise(F.array(F.struct(F.col("place").alias("range"), F.lit(0).alias("guest"))))).alias("s"))
    sent = sent.select("s.range", "s.guest", "doc_id", "text", F.xxhash64("text").alias("tie"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held_: tuple | None = None  # a document that waits for the next
        for x in frames:
            todo = []
            for row in zip(x["range"], x["guest"], x["doc_id"], x["text"], strict=True):
                if held_ is not None:
                    todo.append((held_[2], held_[3], row[3] if row[0] == held_[0] else None))
                    if row[1] or row[0] != held_[0]:
                        held_ = None
                held_ = None if row[1] else row  # of guests only the first counts, as the next of the range's last
            for a, b in S.batches([len(t[1]) for t in todo]):
                yield _compare(todo[a:b])
        if held_ is not None:
            yield _compare([(held_[2], held_[3], None)])

    ordered = sent.repartition(parts(spark), "range").sortWithinPartitions("range", "guest", F.col("doc_id").asc_nulls_first(), "tie")
    return ordered.mapInPandas(lean(run), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


def _compare(rows: list[tuple]) -> pd.DataFrame:
    texts = [r[1] for r in rows]
    after = [r[1] if r[2] is None else r[2] for r in rows]
    changed = [edited(t, n) for t, n in zip(texts, after, strict=True)]
    sig = kept_bits(signatures(texts))
    # Rows follow each other, so the next document's fingerprint is mostly the next row's.
    follows = [i + 1 < len(rows) and after[i] is rows[i + 1][1] for i in range(len(rows))]
    loose = [i for i, f in enumerate(follows) if not f]
    nxt = np.roll(sig, -1, axis=0)
    if loose:
        nxt[loose] = kept_bits(signatures([after[i] for i in loose]))
    new = kept_bits(signatures(changed))
    return pd.DataFrame({
        "doc_id": pd.array([None if pd.isna(r[0]) else int(r[0]) for r in rows], dtype="Int64"), "n_chars": [len(t) for t in texts],
        "edited_sha256": [hashlib.sha256(c.encode("utf-8", "surrogatepass")).hexdigest() for c in changed],
        "fingerprint": printed(sig), "edited_fingerprint": printed(new), "near_edited": likeness(sig, new), "near_next": likeness(sig, nxt),
    })


def bands_of(rows: DataFrame) -> DataFrame:
    """key, leaf: bands of at least two sets."""
    wide = COUNT // BANDS

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            for band in range(BANDS):
                part = [np.frombuffer(v, dtype=np.uint32)[band * wide : (band + 1) * wide].astype(S.U) for v in x["sig"]]
                name = np.full(len(x), band + 1, dtype=S.U)
                for k in range(wide):
                    name = S.mix(name * S.U(0x9E3779B97F4A7C15) + np.array([p[k] for p in part], dtype=S.U))
                yield pd.DataFrame({"key": x["key"].to_numpy(), "leaf": name.view(np.int64)})

    all_ = rows.select("key", "sig").mapInPandas(lean(run), "key binary, leaf long")
    return all_.join(all_.groupBy("leaf").agg(F.count(F.lit(1)).alias("members")).where("members > 1"), "leaf").select("key", "leaf")


def near_copies(docs: DataFrame, threshold: float = 0.8) -> DataFrame:
    """doc_id, class_id, n_links, n_copies of documents whose exact Jaccard similarity reaches the threshold."""
    return links.classes(docs, links.profile(docs, COUNT, SEED), bands_of, COUNT, threshold).drop("dh", "class_dh")
