"""Queries on whole tables, every feature a candidate, against brute force."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from featsift import catalogue
from featsift.operators import baselines, greedy, sampling
from featsift.plans.dataset import Dataset
from featsift.sources import workloads
from featsift.sources.tables import table


def _bits(*columns):
    """Entropy of the joint codes of columns, by feature: each is (rows, 1 or features) of small codes."""
    wide = np.broadcast_arrays(*columns)
    key = np.zeros(wide[0].shape, np.int64)
    for c in wide:
        key = key * 64 + c
    total = np.zeros(key.shape[1])
    for v in np.unique(key):
        p = (key == v).mean(0)
        total -= np.where(p > 0, p * np.log2(np.where(p > 0, p, 1)), 0)
    return total


def brute(x, y, k, criterion):
    """Feature numbers and scores of the first k: all columns of x are candidates in every round."""
    y = y[:, None]
    rel = np.maximum(_bits(x) + _bits(y) - _bits(x, y), 0)
    mi, cmi, steps = [], [], []
    for s in range(k):
        if criterion == "mim" or not s:
            score = rel
        elif criterion == "cmim":
            score = rel - np.max(np.array(mi) - np.array(cmi), 0)
        else:
            score = rel - np.sum(mi, 0) / s + (np.sum(cmi, 0) / s if criterion == "jmi" else 0)
        score = np.round(score, 12)
        score[[f for f, _ in steps]] = -np.inf
        best = int(np.argmax(score))
        steps.append((best, score[best]))
        j = x[:, [best]]
        mi.append(np.maximum(_bits(x) + _bits(j) - _bits(x, j), 0))
        cmi.append(np.maximum(_bits(x, y) + _bits(j, y) - _bits(x, j, y) - _bits(y), 0))
    return steps


@pytest.fixture(scope="module")
def presence(spark, sf_dir):
    """names, row by token presence and toxic labels."""
    labels = {r.doc_id: r.toxic for r in table(spark, sf_dir, "labels").collect()}
    docs = [(set(re.findall("[a-z]+", r.text.lower())), labels[r.doc_id]) for r in table(spark, sf_dir, "documents").collect() if r.doc_id in labels]
    names = sorted(set().union(*[w for w, _ in docs]))
    place = {n: i for i, n in enumerate(names)}
    x = np.zeros((len(docs), len(names)), np.int8)
    for i, (words, _) in enumerate(docs):
        x[i, [place[w] for w in words]] = 1
    return names, x, np.array([y for _, y in docs], np.int8)


@pytest.mark.parametrize("criterion", ["mim", "mrmr", "jmi", "cmim"])
def test_every_token_is_a_candidate(spark, sf_dir, presence, criterion):
    names, x, y = presence
    assert len(names) > 200
    got = catalogue.QUERIES[f"greedy_{criterion}_tokens"](spark, sf_dir).orderBy("step").collect()
    want = brute(x, y, 6, criterion)
    assert [r["name"] for r in got] == [names[f] for f, _ in want]
    assert [r["score"] for r in got] == pytest.approx([s for _, s in want], abs=2e-6)


def test_cells_of_every_token(spark, sf_dir, presence):
    names, x, y = presence
    j = x[:, names.index("idiot")] if "idiot" in names else np.zeros(len(y), np.int8)
    got = {tuple(r) for r in catalogue.QUERIES["cells_sparse_packed"](spark, sf_dir).select("name", "x", "j", "y", "c").collect()}
    want = set()
    for f, n in enumerate(names):
        codes, c = np.unique(np.stack([x[:, f], j, y], 1), axis=0, return_counts=True)
        want |= {(n, *map(int, v), int(k)) for v, k in zip(codes, c)}
    assert got == want


@pytest.mark.parametrize("criterion", ["mim", "mrmr", "jmi", "cmim"])
def test_every_position_is_a_candidate(spark, criterion):
    sf = "/root/testdata/sf0.01"
    rows = workloads.embed(spark, sf).df.toPandas()
    names = [f"e{i}" for i in range(64)]
    got = catalogue.QUERIES[f"greedy_{criterion}_embed"](spark, sf).orderBy("step").collect()
    want = brute(rows[names].to_numpy(np.int8), rows["y"].to_numpy(np.int8), 5, criterion)
    assert [r["name"] for r in got] == [names[f] for f, _ in want]
    assert [r["score"] for r in got] == pytest.approx([s for _, s in want], abs=2e-6)
    assert got[0]["name"] == "e28"  # outside the first 16 positions


def test_rare_tokens_have_a_relevance(spark, sf_dir, presence):
    names, x, y = presence
    got = {r["name"]: r["rel"] for r in catalogue.QUERIES["relevance_tokens_toxic"](spark, sf_dir).collect()}
    rel = np.maximum(_bits(x) + _bits(y[:, None]) - _bits(x, y[:, None]), 0)
    assert x.sum(0).min() == 1 and got == pytest.approx(dict(zip(names, rel)), abs=2e-6)


def test_pages_keep_every_token(spark, sf_dir):
    pages = table(spark, sf_dir, "pages").limit(40).collect()
    words = set().union(*[re.findall("[a-z]+", re.sub("<[^>]*>", " ", r.html).lower()) for r in pages])
    assert words <= {r["name"] for r in catalogue.QUERIES["relevance_pages"](spark, sf_dir).select("name").collect()}


def test_rankings_are_fitted_to_the_training_rows(spark, sf_dir):
    ds = workloads.lines(spark, sf_dir, "noisy")
    train, _ = sampling.holdout(ds.df, F.col("l_orderkey"))
    train = Dataset(train, ds.features)
    fitted = catalogue.fitted_rankings(ds)
    assert fitted == {c: [s["name"] for s in baselines.sequential(train, 5, c)] for c in ("mim", "mrmr", "cmim")}
    assert fitted["mrmr"][2] == "qty_band"


@pytest.mark.parametrize("buckets", [64, 1 << 18])
def test_hashed_sets_equal_their_dense_form(spark, sf_dir, buckets):
    ds = workloads.token_set(spark, sf_dir, "quality", buckets=buckets)
    posts, classes = ds.postings.toPandas(), ds.classes.toPandas().sort_values("row_id")
    features, rows = np.unique(posts["feature"]), {r: i for i, r in enumerate(classes["row_id"])}
    x = np.zeros((len(rows), len(features)), np.int8)
    x[[rows[r] for r in posts["row_id"]], np.searchsorted(features, posts["feature"])] = 1
    got = greedy.select(ds, 5, "mrmr").steps
    want = brute(x, classes["y"].to_numpy(np.int8), 5, "mrmr")
    assert [s["feature"] for s in got] == [features[f] for f, _ in want]
    assert [s["score"] for s in got] == pytest.approx([s for _, s in want], abs=2e-6)
