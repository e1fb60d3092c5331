"""The registered queries of the text operators, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import chunk_dedup, fingerprints, html_extract, jaccard_join, mixing, packing, sharding, suffix_dedup, toxicity, url_trust
from .common import read

Query = Callable[[SparkSession, str], DataFrame]


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op2_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.jaccard_join(read(spark, sf_dir, "documents"))


def op3_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.with_edits(read(spark, sf_dir, "documents"))


def fingerprint_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near copies by bands of the fingerprints of op3, verified exactly."""
    return fingerprints.near_copies(read(spark, sf_dir, "documents"))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(read(spark, sf_dir, "documents"), words=51)


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chunk_dedup.exact_dedup(read(spark, sf_dir, "documents"))


def op6_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract_pages(read(spark, sf_dir, "pages"))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_trust.url_filter(read(spark, sf_dir, "pages")).drop("trust", "distrust")


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_documents(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def tokenizer() -> str:
    """Where the public word tokenizer's file is."""
    import public_tokenizers

    return str(public_tokenizers.path("word_bpe_49k.json"))


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(read(spark, sf_dir, "documents"), tokenizer())


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(read(spark, sf_dir, "documents"))


def queries() -> dict[str, Query]:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f)} | {"fingerprint_classes": fingerprint_classes}


EXACT_SQL = r"""
WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS norm FROM documents)
SELECT doc_id, min(doc_id) OVER (PARTITION BY norm) AS keep_id, count(*) OVER (PARTITION BY norm) AS group_size,
       row_number() OVER (PARTITION BY norm ORDER BY doc_id NULLS LAST) = 1 AS kept, sha256(norm) AS text_sha256
FROM n
"""


def url_sql(rounds: int = 150) -> str:
    """The rules, and propagation as a recursive query.  A node of weight one that only points at itself and at the seeds stands for the restarts."""
    host = "translate(regexp_extract(coalesce({u}, ''), '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    rules = sorted(url_trust.RULES, key=lambda r: (-len(r[1] + r[2]), r))
    fits = lambda r: f"(host = '{r[1]}' OR ends_with(host, '.{r[1]}')) AND starts_with(path, '{r[2]}')"
    case = lambda value: "CASE " + " ".join(f"WHEN {fits(r)} THEN '{value(r)}'" for r in rules) + " END"
    return f"""
    WITH RECURSIVE p AS (SELECT page_id, {host.format(u='url')} AS host, regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path, html FROM pages),
    j AS (SELECT *, {case(lambda r: r[1] + r[2])} AS rule, {case(lambda r: r[0])} AS by_rule FROM p),
    a AS (SELECT host, avg(CASE WHEN by_rule = 'allow' THEN 1.0 ELSE 0.0 END)::DOUBLE AS t, avg(CASE WHEN by_rule = 'block' THEN 1.0 ELSE 0.0 END)::DOUBLE AS d FROM j WHERE host <> '' GROUP BY 1),
    s AS (SELECT host, coalesce(t / nullif(sum(t) OVER (), 0), 0) AS t0, coalesce(d / nullif(sum(d) OVER (), 0), 0) AS d0 FROM a),
    l AS (SELECT host AS src, unnest(regexp_extract_all(coalesce(html, ''), '(?i)href\\s*=\\s*["'']?((?:[a-z][a-z0-9+.-]*:)?//[^"''\\s>]+)', 1)) AS link FROM p),
    e0 AS (SELECT src, translate(regexp_extract(link, '^[^/]*//([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS dst FROM l),
    e AS (SELECT src, dst, count(*) AS n FROM e0 WHERE src <> dst AND src <> '' AND dst <> '' GROUP BY ALL),
    step AS (SELECT src AS from_, dst AS to_, 0.85 * n / sum(n) OVER (PARTITION BY src) AS wt, 0.0 AS wd FROM e UNION ALL
             SELECT dst, src, 0.0, 0.85 * n / sum(n) OVER (PARTITION BY dst) FROM e UNION ALL
             SELECT '*', host, 0.15 * t0, 0.15 * d0 FROM s UNION ALL SELECT '*', '*', 1.0, 1.0),
    r AS (SELECT 0 AS k, host, t0::DOUBLE AS t, d0::DOUBLE AS d FROM s WHERE EXISTS (SELECT 1 FROM e) UNION ALL SELECT 0, '*', 1.0, 1.0 WHERE EXISTS (SELECT 1 FROM e) UNION ALL
          SELECT any_value(r.k) + 1, x.to_, sum(r.t * x.wt), sum(r.d * x.wd) FROM r JOIN step x ON r.host = x.from_ WHERE r.k < {rounds} GROUP BY x.to_),
    g AS (SELECT host, t0 AS t, d0 AS d FROM s WHERE NOT EXISTS (SELECT 1 FROM e) UNION ALL SELECT host, t, d FROM r WHERE k = {rounds})
    SELECT page_id, j.host, path, rule, coalesce(by_rule, CASE WHEN coalesce(d, 0) > coalesce(t, 0) THEN 'block' ELSE 'allow' END) AS verdict
    FROM j LEFT JOIN g ON g.host = j.host
    """.replace("\\\\s", "\\s")


def oracle_sql() -> dict[str, str]:
    return {"op5_exact_dedup": EXACT_SQL, "op7_url_filter": url_sql()}
