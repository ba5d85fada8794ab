"""Text sets: the short way of selections and studies against postings, brute force and the library."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from featsift import catalogue
from featsift.operators import greedy, metrics, models, pooled, sampling
from featsift.plans import tokens
from featsift.sources import workloads


def key(found):
    return [(s["step"], s["feature"], s["name"], round(s["score"], 9), round(s["rel"], 9)) for s in found.steps]


@pytest.mark.parametrize("how", [{}, {"ngram": 2}, {"buckets": 1 << 12}])
@pytest.mark.parametrize("criterion", ["mrmr", "icap"])
def test_few_tokens_select_as_all_do(spark, sf_dir, monkeypatch, how, criterion):
    """A pool that has to grow, tokens counted in several turns, and no postings."""
    want = key(greedy.select(workloads.token_set(spark, sf_dir, "quality", **how).full, 8, criterion))
    monkeypatch.setattr(pooled, "POOL", 10)
    monkeypatch.setattr(tokens, "HELD", 500)
    monkeypatch.setattr(tokens, "BLOCK_ENTRIES", 50)
    for made in ("to_postings", "hashed_postings"):
        monkeypatch.setattr(workloads, made, None)
    assert key(greedy.select(workloads.token_set(spark, sf_dir, "quality", **how), 8, criterion)) == want


def written(spark, path, docs, labels):
    spark.createDataFrame(docs, "doc_id long, text string, lang string").write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return str(path)


def test_odd_texts(spark, tmp_path):
    """Null, empty and unlabelled texts; an id of two texts takes the long way."""
    docs = [(i, t, "en") for i, t in enumerate([None, "", "KIT a 1 b", "a b\n a b", "b c", "A c kit", "a", "c d"])]
    labels = [(i, int(i % 3 == 0), 0) for i in range(7)]
    for n, more in enumerate(([], [(3, "a z", "en")])):
        d = written(spark, tmp_path / str(n), docs + more, labels)
        ds = workloads.token_set(spark, d, "quality")
        assert ds.plain == (not more) and ds.n == 7
        assert key(greedy.select(ds, 4, "mrmr")) == key(greedy.select(ds.full, 4, "mrmr"))
    assert workloads.token_set(spark, written(spark, tmp_path / "none", docs[:2], labels), "quality").size == 0


def test_presence_of_the_chosen(spark, sf_dir):
    """Grouped rows of both sides, those without any chosen token included, are what postings say."""
    ds = workloads.token_set(spark, sf_dir, "quality")
    train = ds.within(sampling.trains(F.col("row_id")))
    found = greedy.select(train, 6, "mrmr")
    for k in (2, 6):
        want = models.presence_vectors(ds, [s["feature"] for s in found.steps[:k]]).withColumn("inside", sampling.trains(F.col("row_id")))
        want = sorted((r["inside"], r["y"], *r["v"].toArray()) for r in want.collect())
        rows = models.restricted(train.presence(found.blocks, found.places), k)
        got = [(side, r["y"], *r["v"].toArray()) for side in (True, False) for r in models.present(rows.where(F.col("inside") == side), k).collect() for _ in range(r["weight"])]
        assert sorted(got) == want and len(got) > 50


@pytest.mark.parametrize("classifier", ["nb", "sgd", "svm"])
def test_studies_of_texts_make_no_postings(spark, sf_dir, monkeypatch, classifier):
    """Grouped rows give the area that single rows of postings give."""
    ds = workloads.token_set(spark, sf_dir, "quality")
    found = greedy.select(ds.within(sampling.trains(F.col("row_id"))), 5, "mrmr")
    train, test = sampling.holdout(models.presence_vectors(ds, [s["feature"] for s in found.steps]), F.col("row_id"))
    ranked = models.scored(catalogue._FITS[classifier](train.drop("row_id")), test).withColumn("score", F.round("score", 10))
    want = metrics.auc(ranked).first()["auc"]
    monkeypatch.setattr(workloads, "to_postings", None)
    rows = catalogue.classifier_study(spark, sf_dir, "quality", classifier, (5,)).collect()
    # two optimisers of one cost end near each other, not at the same place
    assert [r["k"] for r in rows] == [5] and float(rows[0]["auc"]) == pytest.approx(float(want), abs=0.2 if classifier == "svm" else 1e-9)


@pytest.mark.parametrize("local", [0, 1 << 20])
def test_hinge_of_grouped_rows(spark, monkeypatch, local):
    """Weighted rows reach the minimum of the single ones' cost, on the driver and by jobs."""
    from pyspark.ml.functions import vector_to_array

    monkeypatch.setattr(models, "LOCAL_BYTES", local)
    rows = workloads.lines(spark, "/root/testdata/sf0.001", "noisy").df.where("l_orderkey < 300")
    encode_ = models.OneHot(rows, ["disc", "tax"])
    single = encode_(rows).select(vector_to_array("v").alias("x"), "y").toPandas()
    x, sign = np.array(single["x"].tolist()), 2 * single["y"].to_numpy() - 1
    scale = x.std(0, ddof=1)

    def cost(m, w, b):
        return np.maximum(0, 1 - sign * (x @ w + b)).mean() + m * ((scale * w) ** 2).sum() / 2

    model = models.svm(models.packed(encode_(models.grouped(rows, ["disc", "tax"]))))
    got = cost(1.0, model.weights, model.intercept)
    # the cost is convex: no nearby place is lower
    step = np.random.default_rng(1).standard_normal((200, x.shape[1] + 1)) * 0.1
    assert all(got < cost(1.0, model.weights + s[:-1], model.intercept + s[-1]) + 1e-4 for s in step)


@pytest.mark.parametrize("buckets", [1, 64, 1000, 999983, 1 << 20])
def test_tokens_are_hashed_as_by_spark(spark, sf_dir, buckets):
    from pyspark.sql import functions as F

    from featsift.functions import encode
    from featsift.plans.tokens import _split
    from featsift.sources.tables import table

    docs = table(spark, sf_dir, "documents").limit(40)
    words = F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))
    for n in (1, 2):
        hashes = F.transform(words if n == 1 else encode.ngrams(words, n), lambda t: encode.hashed(t, buckets))
        rows = docs.where("text IS NOT NULL").select(F.lower("text").alias("text"), hashes.alias("hashes")).collect()
        split = _split(n, buckets)
        assert rows and all(split(r["text"]) == set(r["hashes"]) for r in rows)
