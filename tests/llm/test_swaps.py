import random

import numpy as np
import pytest

from featsift.llm import toxicity


def test_every_term_is_swapped_for_every_other_and_added_where_there_is_none():
    cf = toxicity.counterfactuals([["a", "c"], ["b"], []], ["a", "b", "c", "d"])
    got = {(t, o): cf.weight[k].tolist() for t, o, k in zip(cf.text.tolist(), cf.out.tolist(), cf.kind)}
    assert got == {(0, 0): [0, 0.25, 0, 0.25], (0, 2): [0, 0.25, 0, 0.25], (1, 1): pytest.approx([1 / 3, 0, 1 / 3, 1 / 3]), (2, -1): [0.25] * 4}


@pytest.mark.parametrize("most", [10**6, 10])
def test_slopes_of_score_changes(monkeypatch, most):
    """Against differences of the summed squared score changes; taking turns covers the same swaps."""
    monkeypatch.setattr(toxicity, "MOST_AT_ONCE", most)
    rng = np.random.default_rng(1)
    cf = toxicity.counterfactuals([["a", "c"], ["b"], [], []], ["a", "b", "c", "d"])
    z, total = rng.standard_normal(4), rng.standard_normal(4)
    sigma = lambda x: 1 / (1 + np.exp(-x))

    def loss(z, total):
        changed = sigma((z[cf.text] - np.where(cf.out >= 0, total[cf.out], 0))[:, None] + total[None, :])
        return (cf.weight[cf.kind] * (changed - sigma(z)[cf.text][:, None]) ** 2).sum()

    turns = [toxicity.score_changes(cf, z, sigma(z), total, turn) for turn in range(4)]
    by_text, by_term = (np.mean(x, axis=0) for x in zip(*turns))
    for i in range(4):
        step = np.eye(4)[i] * 1e-6
        assert by_text[i] == pytest.approx((loss(z + step, total) - loss(z - step, total)) / 2e-6, abs=1e-5)
        assert by_term[i] == pytest.approx((loss(z, total + step) - loss(z, total - step)) / 2e-6, abs=1e-5)


def biased(spark, seed):
    """Most toxic texts name a group, few others do."""
    rng = random.Random(seed)
    fill = lambda: " ".join(rng.choices(["river", "house", "green", "walk", "paper"], k=6))
    rows = []
    for i in range(400):
        bad = rng.random() < 0.4
        named = rng.random() < (0.6 if bad else 0.05)
        rows.append((i, " ".join([fill(), "scum" if bad and rng.random() < 0.8 else "", rng.choice(["muslims", "women", "young"]) if named else "", fill()]), int(bad)))
    return spark.createDataFrame(rows, "doc_id long, text string, toxic int"), fill


def test_penalty_lowers_false_positives_on_neutral_mentions(spark):
    docs, fill = biased(spark, 8)
    args = docs.select("doc_id", "text"), docs.select("doc_id", "toxic")
    model, free = toxicity.fit(*args), toxicity.fit(*args, counterfactual=0.0)
    assert model.weights != free.weights and model.word_weight("scum") > 1
    for term in ("muslims", "women", "young"):
        assert abs(model.word_weight(term)) < 0.7 * abs(free.word_weight(term))
    neutral = spark.createDataFrame([(i, f"{fill()} {t} {fill()}") for i, t in enumerate(toxicity.IDENTITY_TERMS)] + [(1000, "scum " + fill())], "doc_id long, text string")
    flagged = [{r.doc_id for r in toxicity.toxicity_scores(neutral, m).collect() if r.score >= 0.3} for m in (model, free)]
    assert flagged[0] == {1000} and {1000} < flagged[1]


def test_given_labels_leave_neutral_mentions_alone(spark):
    """The given labels name no group, but stems that identity terms share with other words carry weight without the penalty."""
    sf = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    model, free = toxicity.fit(docs, labels), toxicity.fit(docs, labels, counterfactual=0.0)
    change = [[abs(m.word_weight(t)) for t in toxicity.IDENTITY_TERMS] for m in (model, free)]
    assert max(change[0]) <= max(change[1])
    if max(change[1]) > 0:
        assert model.weights != free.weights and sum(change[0]) < sum(change[1])


def test_terms_late_in_the_alphabet_are_cleared_too(spark):
    """young stands beside black in every toxic text of a few; a neutral mention of it isn't toxic."""
    rows = [(i, f"black young talk {('fool', 'trash')[i % 2]} again", 1) for i in range(14)]
    rows += [(100 + i, f"white garden number {'xyz'[i % 3]}", 0) for i in range(26)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    model = toxicity.fit(docs.select("doc_id", "text"), docs.select("doc_id", "toxic"))
    # they always stand together, so what clears one clears the other
    assert model.word_weight("young") == pytest.approx(model.word_weight("black"), abs=1e-6)
    assert abs(model.word_weight("young")) < model.word_weight("fool")


def test_repeated_ids_long_texts_and_nulls(spark):
    docs, _ = biased(spark, 2)
    labels = docs.select("doc_id", "toxic").union(docs.select("doc_id", "toxic"))
    rows = spark.createDataFrame([(1, "scum", "x"), (1, "river", "x"), (None, "scum", "x"), (5, None, "x"), (6, "", "x"), (7, "river " * 50_000 + "scum", "x")], "doc_id long, text string, score string")
    model = toxicity.fit(docs.select("doc_id", "text"), labels)
    got = [r.score for r in toxicity.toxicity_scores(rows, model).collect()]
    assert got[0] == got[2] > got[1] and got[3] == got[4] and got[5] > got[1]
    assert toxicity.classify(rows, labels).where("doc_id IS NULL").first().held_out
