"""Counterfactual-regularised toxicity classifier.

A logistic model over the words and word stems of a text.  Stems matter because insults inflect.  Besides the
likelihood, training minimises the mean squared change of the score when a labelled text is rewritten: each of its
identity terms is swapped for every other one, and a text that names no group gets a neutral mention of each.  The words
and stems of identity terms are always features, so whatever weight the labels alone would give to the names of groups,
or to stems they share with other words, is pulled back as far as it changes scores.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import id_text

#: Labelled rows used for training at most, taken in the order of a hash of their ids.
MAX_LABELLED = 20_000
#: Features: words and stems found in so many toxic texts, with so many times the usual odds of a toxic text, and at most this many.
LEAST_TOXIC, LEAST_LIFT, MAX_FEATURES = 3, 3.0, 20_000
L2, COUNTERFACTUAL, ROUNDS = 0.02, 10.0, 400
#: Rewritten texts looked at in one round; of more, the rounds take turns, each with every so many replacements.
MOST_AT_ONCE = 400_000

#: Neutral names of groups in the corpus' languages (fixed values).
IDENTITY_TERMS = tuple(
    "women men woman man girls boys black white asian african european american latino indian chinese mexican arab muslim muslims jewish jews christian "
    "christians hindu buddhist catholic atheist gay lesbian bisexual transgender straight immigrant immigrants refugee refugees disabled deaf blind elderly "
    "young poor frauen männer schwarze weiße muslime juden christen schwule lesben einwanderer flüchtlinge behinderte femmes hommes noirs blancs musulmans "
    "juifs chrétiens gays lesbiennes immigrés réfugiés handicapés mujeres hombres negros blancos musulmanes judíos cristianos inmigrantes refugiados".split()
)
_WORD = re.compile(r"[^\W\d_]+")


def features_of(word: str) -> tuple[str, ...]:
    """The word itself and its stems of four and five letters."""
    return tuple(["=" + word, *(word[:n] for n in (4, 5) if len(word) >= n)])


def distinct_words(text: str) -> set[str]:
    return set(_WORD.findall(text.lower()))


@dataclass
class ToxicityModel:
    bias: float
    weights: dict[str, float]

    def word_weight(self, word: str) -> float:
        return sum(self.weights.get(f, 0.0) for f in features_of(word))


class _WordWeights(dict):
    def __init__(self, model: ToxicityModel, most: int = 500_000):
        self.model, self.most = model, most

    def __missing__(self, word: str) -> float:
        w = self.model.word_weight(word)
        if len(self) < self.most:
            self[word] = w
        return w


def train_ids(doc_id: Column) -> Column:
    """Rows whose labels may be learnt: crc32 of the id as text, modulo 4, isn't 2."""
    return doc_id.isNotNull() & (F.crc32(doc_id.cast("string").cast("binary")) % 4 != 2)


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, most: int, keep: Column | None = None) -> DataFrame:
    """doc_id, text, y of at most ``most`` labelled documents; the ids that are broadcast are bounded by it."""
    ids = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y")).where("y IN (0, 1) AND doc_id IS NOT NULL")
    if keep is not None:
        ids = ids.where(keep)
    ids = ids.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    return docs.join(F.broadcast(ids), "doc_id")


@dataclass
class Counterfactuals:
    """One row for each text and term taken out (-1: none, the text names no group); the columns are the terms put in."""

    text: np.ndarray
    out: np.ndarray
    kind: np.ndarray
    #: How much a replacement counts, by kind of row: those of one text count 1 together, terms it has already count 0.
    weight: np.ndarray


def counterfactuals(mentioned: list[list[str]], terms: list[str]) -> Counterfactuals:
    """Every swap of an identity term for another one, and every addition of one to a text that names none."""
    number = {t: i for i, t in enumerate(terms)}
    text, out, kind, weights, kinds = [], [], [], [], {}
    for i, group in enumerate(map(tuple, mentioned)):
        here = [number[t] for t in group]
        if group not in kinds:
            free = len(terms) - len(here)
            w = np.full(len(terms), 1 / (max(1, len(here)) * free) if free else 0.0)
            w[here] = 0.0
            kinds[group] = len(weights)
            weights.append(w)
        for t in here or [-1]:
            text.append(i)
            out.append(t)
            kind.append(kinds[group])
    return Counterfactuals(np.array(text, np.int64), np.array(out, np.int64), np.array(kind, np.int64), np.array(weights).reshape(-1, len(terms)))


def _logistic(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -500, 500)))


def score_changes(cf: Counterfactuals, z: np.ndarray, p: np.ndarray, total: np.ndarray, turn: int) -> tuple[np.ndarray, np.ndarray]:
    """Slopes of the summed squared score changes: by the log odds of each text, and by the weight of each term."""
    if not len(cf.text) or not len(total):
        return np.zeros(len(z)), np.zeros(len(total))
    stride = min(len(total), -(-len(cf.text) * len(total) // MOST_AT_ONCE))
    into = np.arange(turn % stride, len(total), stride)
    gone = cf.out >= 0
    base = z[cf.text] - np.where(gone, total[cf.out], 0.0)
    q = _logistic(base[:, None] + total[into][None, :])
    pull = 2 * stride * cf.weight[cf.kind][:, into] * (q - p[cf.text][:, None])
    moved = pull * q * (1 - q)
    own = p[cf.text] * (1 - p[cf.text])
    by_text = np.bincount(cf.text, moved.sum(1) - pull.sum(1) * own, len(z))
    by_term = np.zeros(len(total))
    by_term[into] = moved.sum(0)
    by_term -= np.bincount(cf.out[gone], moved.sum(1)[gone], len(total))
    return by_text, by_term


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", most: int = MAX_LABELLED, identity: tuple[str, ...] = IDENTITY_TERMS, counterfactual: float = COUNTERFACTUAL) -> ToxicityModel:
    """docs: doc_id, text; labels: doc_id and the label.

    Held-out labels aren't read.  Of labels that repeat an id the greatest counts; rows that repeat an id are as many
    examples.  Without labels of both kinds every score is the share of toxic ones (0.5 with none).
    """
    sample = labelled_sample(docs, labels, label, most, train_ids(F.col("doc_id")))

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for text in batch.column(0).to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array(sorted({f for w in distinct_words(text) for f in features_of(w)}), pa.string())], names=["feature"])

    terms = list(dict.fromkeys(identity))
    toxic = sample.where("y = 1").select("text").mapInArrow(spread, "feature string").groupBy("feature").count().where(F.col("count") >= LEAST_TOXIC)
    names = [r["feature"] for r in toxic.orderBy(F.desc("count"), "feature").limit(10 * MAX_FEATURES).collect()]
    names = list(dict.fromkeys([*names, *(f for t in terms for f in features_of(t))]))
    number = {f: i for i, f in enumerate(names)}
    shared = docs.sparkSession.sparkContext.broadcast(number)

    def present(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, mentions = shared.value, set(identity)
        for batch in batches:
            found, groups = [], []
            for text in batch.column(0).to_pylist():
                words = distinct_words(text)
                found.append(np.array(sorted(known[f] for w in words for f in features_of(w) if f in known), np.int32).tobytes())
                groups.append(sorted(words & mentions))
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(found, pa.binary()), pa.array(groups, pa.list_(pa.string()))], names=["y", "found", "groups"])

    rows = sample.select("text", "y").mapInArrow(present, "y int, found binary, groups array<string>").collect()
    shared.unpersist()
    y = np.array([r["y"] for r in rows], np.float64)
    if not len(y) or y.min() == y.max():
        share = min(max(float(y.mean()), 0.01), 0.99) if len(y) else 0.5
        return ToxicityModel(float(np.log(share / (1 - share))), {})
    # packed integers: a few bytes for each feature of a sampled text, once for each word that has it
    column = np.frombuffer(b"".join(r["found"] for r in rows), np.int32)
    row = np.repeat(np.arange(len(rows), dtype=np.int32), [len(r["found"]) // 4 for r in rows])
    cf = counterfactuals([r["groups"] for r in rows], terms)
    del rows
    once = np.ones(len(row), bool)
    once[1:] = (row[1:] != row[:-1]) | (column[1:] != column[:-1])
    seen, hits = np.bincount(column[once], minlength=len(names)), np.bincount(column[once], y[row[once]], len(names))
    lift = (hits / (seen - hits + 0.5)) / (y.mean() / (1 - y.mean()))  # of the odds
    chosen = np.flatnonzero((lift >= LEAST_LIFT) & (hits >= LEAST_TOXIC))
    chosen = chosen[np.argsort(-(hits[chosen] * np.log(lift[chosen])), kind="stable")][:MAX_FEATURES]
    chosen = np.concatenate((chosen, np.setdiff1d([number[f] for t in terms for f in features_of(t)], chosen))).astype(np.int64)
    place = np.full(len(names), -1, np.int32)
    place[chosen] = np.arange(len(chosen))
    inside = place[column] >= 0
    row, column = row[inside], place[column[inside]]
    where = {names[c]: i for i, c in enumerate(chosen)}
    # what the weights of the features of a term add up to
    parts = np.zeros((len(terms), len(chosen)))
    for t, term in enumerate(terms):
        for f in features_of(term):
            parts[t, where[f]] += 1.0
    used = np.flatnonzero(parts.any(0))
    parts = parts[:, used]
    w, b, n = np.zeros(len(chosen)), float(np.log(y.mean() / (1 - y.mean()))), len(y)
    speed, bias_speed = np.zeros_like(w), 0.0
    for turn in range(ROUNDS):
        z = b + np.bincount(row, w[column], n)
        p = _logistic(z)
        error, by_term = p - y, np.zeros(len(terms))
        if counterfactual and len(terms) > 1:
            by_text, by_term = score_changes(cf, z, p, parts @ w[used], turn)
            error = error + counterfactual * by_text
        slope = np.bincount(column, error[row], len(w)) / n + L2 * w / 100
        slope[used] += counterfactual * parts.T @ by_term / n
        speed, bias_speed = 0.9 * speed - 2.0 * slope, 0.9 * bias_speed - 0.5 * error.mean()
        w, b = w + speed, b + bias_speed
    return ToxicityModel(b, {names[c]: float(v) for c, v in zip(chosen, w)})


def toxicity_scores(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and score (0 to 1) per row.  Null or empty text: the score of the bias alone.  Every row is scored on its own; an empty table gives no rows; other columns are ignored."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: ToxicityModel = shared.value
        weight = _WordWeights(m)
        for batch in batches:
            sums = [m.bias + sum(map(weight.__getitem__, distinct_words(t.as_py()))) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(1 / (1 + np.exp(-np.clip(np.array(sums), -500, 500))), pa.float64())], names=["doc_id", "score"])

    return id_text(docs, id_col, text_col).mapInArrow(run, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score and predicted (1 if the score reaches the threshold), one row per row of ``docs``.

    A null id counts as held out.  Rows that repeat an id are scored each.  Null and empty texts have the score of the
    bias; long texts are read whole.  An empty table gives no rows; other columns are ignored.
    """
    rows = id_text(docs)
    found = toxicity_scores(rows, fit(rows, labels))
    return found.select("doc_id", (~train_ids(F.col("doc_id"))).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
