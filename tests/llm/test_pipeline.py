"""Each pipeline stage against a plain computation, on documents with repeated rows, repeated ids, nulls and clashing columns."""

import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_operators import brute_classes

import corpus_pipeline
from privsurv.llm import mixing, toxicity
from privsurv.llm.common import read, ready

STAGE = dict(corpus_pipeline.STAGES)
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, __score string, __rate string, __copy string, __id string, __dh string, __hash string"


def row(i, text):
    return (i, text, "en", "s", None if text is None else len(text), *["kept"] * 6)


def words(r, n, pool=4000):
    return " ".join(f"w{r.randrange(pool)}" for _ in range(n))


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """Documents and labels: toxic ones use a few words that clean ones don't."""
    ready(spark)
    r, rows, labels = random.Random(8), [], []
    for i in range(160):
        bad = i % 4 == 0
        text = words(r, 60) + (" vilebad hatefulword" * 3 if bad else "")
        rows.append(row(i, text))
        labels.append((i, r.randrange(2), int(bad)))
    base = words(r, 100).split()
    for i in range(160, 190):  # a family of near copies
        own = list(base)
        own[r.randrange(100)] = f"x{i}"
        rows.append(row(i, " ".join(own)))
    rows += [row(7, rows[7][1]), row(7, rows[7][1]), row(300, rows[9][1].replace(" ", "  ")), row(9, rows[9][1].replace(" ", "\t")), row(5, rows[161][1]), row(161, words(r, 30))]
    rows += [row(301, None), row(302, ""), row(None, None), row(303, " \n"), row(None, rows[11][1]), row(304, words(r, 9000))]
    path = str(tmp_path_factory.mktemp("pipeline"))
    spark.createDataFrame(rows, COLUMNS).repartition(3).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return path


def pairs(df):
    return Counter((r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect())


def stage(spark, folder, name):
    docs = read(spark, folder, "documents")
    out = STAGE[name](spark, docs, folder)
    assert out.columns == docs.columns and out.where("__score <> 'kept' or __copy <> 'kept' or __id <> 'kept'").isEmpty()
    return docs, out


def test_toxic_documents_go(spark, folder):
    docs, out = stage(spark, folder, "toxicity")
    model = toxicity.train_on(docs, read(spark, folder, "labels"))
    have = pairs(docs)
    texts = sorted({t or "" for _, t in have})
    score = dict(zip(texts, toxicity.score(model, texts)[0], strict=True))
    assert pairs(out) == Counter({k: n for k, n in have.items() if score[k[1] or ""] < 0.5})
    left = {i for i, _ in pairs(out)}
    assert not left & set(range(0, 160, 4)) and left >= set(range(1, 160, 4))


def normal(t):
    return re.sub(r"[\x20\x09-\x0D]+", " ", t or "")


def least(keys):
    return min(keys, key=lambda k: (k[0] is None, k[0] or 0))


def test_one_row_of_equal_texts_stays(spark, folder):
    docs, out = stage(spark, folder, "exact_dedup")
    groups = {}
    for k in pairs(docs):
        groups.setdefault(normal(k[1]), []).append(k)
    got = pairs(out)
    assert set(got.values()) == {1} and sorted(normal(t) for _, t in got) == sorted(groups)
    assert all(i == least(groups[normal(t)])[0] for i, t in got)


def test_one_row_of_each_class_stays(spark, folder):
    docs, out = stage(spark, folder, "jaccard_join")
    have = sorted(pairs(docs), key=lambda k: (k[0] is None, k[0] or 0, k[1] or ""))
    classes = brute_classes([(k, (have[k][1] or "").strip()) for k in range(len(have))])
    groups = {}
    for k, (first, _) in classes.items():
        groups.setdefault(first, []).append(have[k])
    got = pairs(out)
    assert set(got.values()) == {1} and len(got) == len(groups)
    assert Counter(i for i, _ in got) == Counter(least(g)[0] for g in groups.values())


def test_mixing_copies_by_the_rates_of_the_whole_table(spark, folder):
    docs, out = stage(spark, folder, "mixing")
    found, _ = mixing.fit_mix(docs, mixing.domains(read(spark, folder, "labels")), mixing.WEIGHTS, budget="grow", least=1.0)
    have, got = pairs(docs), pairs(out)
    texts = sorted({t or "" for _, t in have})
    n, p = mixing.posteriors(found.classifier, texts)
    rate = dict(zip(texts, mixing.rates(p, found.history, found.size, 1.0)[1], strict=True))
    assert set(got) == set(have)
    assert all(k * int(rate[key[1] or ""]) <= got[key] <= k * (int(rate[key[1] or ""]) + 1) for key, k in have.items())
    totals = sum(have[k] * rate[k[1] or ""] * n[texts.index(k[1] or "")] * p[texts.index(k[1] or "")] for k in have)
    assert np.allclose(totals, found.totals, rtol=1e-6) and found.gap < 0.01


def test_packing_places_every_row(spark, folder):
    docs = read(spark, folder, "documents")
    out = STAGE["packing"](spark, docs, folder)
    first = Counter(r["doc_id"] for r in out.where("piece = 0").select("doc_id").collect())
    assert first == Counter(r["doc_id"] for r in docs.select("doc_id").collect())
    own = out.groupBy("sequence_id").agg(F.sum("length").alias("n"), F.max(F.col("offset") + F.col("length")).alias("end"))
    assert own.where("n > 4096 or n <> end").isEmpty()
