import math
import random
import struct
import zlib
from collections import Counter

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from featsift.llm import chat, embedding_dedup, ngram_lm, packing, quality, sentencepiece_codec, toxicity
from featsift.llm.queries import tokenizer_file

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, host string, score double"


def frame(spark, texts, ids=None):
    ids = range(len(texts)) if ids is None else ids
    return spark.createDataFrame([(i, t, "en", f"s{k % 3}", None, "h", 0.0) for k, (i, t) in enumerate(zip(ids, texts))], SCHEMA)


TEXTS = ["hello world, it's 12 o'clock", None, "", "  two  blanks\n\n x", "a<|endoftext|>b", "é ü 😀 " * 400, "x" * 3000, "the cat " * 900, "the cat " * 900]


def test_packing_places_every_id_once(spark):
    from tokenizers import Tokenizer

    path = tokenizer_file("byte_bpe_50k.json")
    rows = packing.pack(frame(spark, TEXTS).repartition(3), path, capacity=64).collect()
    t = Tokenizer.from_file(path)
    ids = {i: t.encode(x or "", add_special_tokens=False).ids + [0] for i, x in enumerate(TEXTS)}
    cover = {i: np.zeros(len(v), int) for i, v in ids.items()}
    windows = {}
    for r in rows:
        part = ids[r.doc_id][r.start : r.start + r.length]
        assert len(part) == r.length and r.doc_tokens == len(ids[r.doc_id])
        assert r.ids_crc32 == zlib.crc32(struct.pack(f"<{len(part)}I", *part))
        cover[r.doc_id][r.start : r.start + r.length] += 1
        windows.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert all((c == 1).all() for c in cover.values())
    for pieces in windows.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 64
    total = sum(len(v) for v in ids.values())
    assert len(windows) <= math.ceil(total / 64) + 2
    assert packing.pack(frame(spark, []), path).count() == 0


def test_rows_without_id_and_with_repeated_ids_are_texts_of_their_own(spark):
    texts, ids = ["one two", "three", "three", None, "x " * 5000], [7, 7, None, None, 7]
    pieces = packing.pack(frame(spark, texts, ids), tokenizer_file("byte_bpe_50k.json")).collect()
    assert sorted(str(r.doc_id) for r in pieces if r.start == 0) == ["7", "7", "7", "None", "None"]
    path = tokenizer_file("piece_bpe_32k.model")
    coded = sentencepiece_codec.codec_digest(frame(spark, texts, ids), path)
    assert coded.count() == 5 and coded.where("doc_id IS NULL").count() == 2
    assert sentencepiece_codec.codec_digest(frame(spark, []), path).count() == 0
    scores = ngram_lm.language_scores(frame(spark, texts, ids)).collect()
    assert sorted((str(r.doc_id), r.n_tokens, r.held_out) for r in scores) == [("7", 2, False), ("7", 3, False), ("7", 5001, False), ("None", 1, True), ("None", 2, True)]


def test_bin_slack_plan_uses_up_the_histogram():
    rng = random.Random(2)
    for _ in range(20):
        histogram = {rng.randint(1, 100): rng.randint(1, 50) for _ in range(rng.randint(1, 30))}
        used = Counter()
        for often, pattern in packing.plan_windows(dict(histogram), 100):
            assert sum(x * k for x, k in pattern.items()) <= 100
            for x, k in pattern.items():
                used[x] += often * k
        assert used == Counter(histogram)
    assert packing.closest_multiset({40: 3, 25: 1, 7: 2}, 94) == {40: 2, 7: 2}


def test_codec_equals_the_library(spark):
    import sentencepiece

    path = tokenizer_file("piece_bpe_32k.model")
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = [*TEXTS, "▁ ▁x", "\tq\n\n", "<s> </s>"]
    for r in sentencepiece_codec.encode_decode(frame(spark, texts), path).collect():
        want = [model.bos_id(), *model.encode(texts[r.doc_id] or ""), model.eos_id()]
        assert list(memoryview(bytes(r.ids)).cast("I")) == want and r.n_tokens == len(want) and r.decoded == model.decode(want)


def test_embedding_links_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(embedding_dedup, "BLOCK", 16)
    rng = np.random.default_rng(4)
    base = rng.standard_normal((30, 16))
    x = [base[rng.integers(30)] + rng.standard_normal(16) * rng.choice([0.0, 0.02, 0.1, 0.3]) for _ in range(240)]
    x = [v.tolist() for v in x] + [None, [], [0.0] * 16, [float("nan")] * 16, [None] * 16, x[0].tolist(), (2 * x[0]).tolist(), [1.0, 2.0]]
    df = spark.createDataFrame([(i, v, "k") for i, v in enumerate(x)], "vec_id long, embedding array<double>, key string")
    got = {r.vec_id: (r.n_links, r.component_id) for r in embedding_dedup.near_vectors(df.repartition(3)).collect()}
    usable = [v if v and all(c is not None and math.isfinite(c) for c in v) and any(v) else None for v in x]
    root, links = list(range(len(x))), Counter()

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(usable):
        for j in range(i):
            b = usable[j]
            if a and b and len(a) == len(b) and np.dot(a, b) / np.linalg.norm(a) / np.linalg.norm(b) >= 0.95:
                links[i] += 1
                links[j] += 1
                p, q = sorted((find(i), find(j)))
                root[q] = p
    want = {i: (links[i], find(i)) for i in range(len(x))}
    assert all(got[i][0] <= want[i][0] for i in want)
    assert sum(g[0] for g in got.values()) >= 0.95 * sum(w[0] for w in want.values())
    assert sum(got[i] == want[i] for i in want) >= 0.9 * len(want)
    assert got[240] == (0, 240)
    assert embedding_dedup.near_vectors(df.limit(0)).count() == 0


def test_sketches_keep_pairs_at_the_threshold():
    bound = embedding_dedup.sketch_bound(0.95)
    assert 20 < bound < 45
    rng = np.random.default_rng(9)
    a = rng.standard_normal((3000, 24))
    a /= np.linalg.norm(a, axis=1)[:, None]
    b = rng.standard_normal((3000, 24))
    b -= (a * b).sum(1)[:, None] * a
    b = 0.95 * a + math.sqrt(1 - 0.95**2) * b / np.linalg.norm(b, axis=1)[:, None]
    words = (embedding_dedup.sketches(a) ^ embedding_dedup.sketches(b)).view(np.uint64)
    assert np.bitwise_count(words).sum(axis=1).max() <= bound


@pytest.mark.parametrize("segment_bytes", [1 << 30, 4000])
def test_language_scores(spark, segment_bytes):
    rng = random.Random(6)
    words = [f"w{i}" for i in range(60)]
    texts = [" ".join(rng.choices(words, k=rng.randint(0, 40))) for _ in range(80)] + [None, "Never SEEN words\there", "W1 w2"]
    got = {r.doc_id: r for r in ngram_lm.language_scores(frame(spark, texts).repartition(4), segment_bytes=segment_bytes).collect()}
    split = [[*(t or "").lower().split(), None] for t in texts]
    train = [s for i, s in enumerate(split) if zlib.crc32(str(i).encode()) % 10]
    one, two = Counter(w for s in train for w in s), Counter(p for s in train for p in zip([None, *s], s))
    n, v = sum(one.values()), len(one)
    exact = 0
    for i, s in enumerate(split):
        r = got[i]
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(s), sum(one[w] > 0 for w in s), n)
        assert r.held_out == (zlib.crc32(str(i).encode()) % 10 == 0)
        base = lambda w: (one[w] + 0.1) / (n + 0.1 * (v + 1))
        assert r.base_score == pytest.approx(sum(math.log10(base(w)) for w in s))
        want = 0.0
        for a, b in zip([None, *s], s):
            c = min(float(ngram_lm.estimate(ngram_lm.levels(np.array([two[(a, b)]])))[0]), one[a], one[b]) if two[(a, b)] else 0.0
            want += math.log10(0.7 * base(b) + 0.3 * (c / one[a] if one[a] else base(b)))
        exact += abs(r.score - want) < 0.05 * max(1, abs(want))
    assert exact >= 0.9 * len(split)  # the filter may see a pair that isn't there


def test_language_scores_of_nothing(spark):
    assert ngram_lm.language_scores(frame(spark, [])).count() == 0
    assert ngram_lm.language_scores(frame(spark, ["a"], [None])).first().held_out


def test_quantised_counts():
    c = np.arange(1, 5000)
    e = ngram_lm.estimate(ngram_lm.levels(c))
    assert (np.diff(e) >= 0).all() and (np.abs(np.log(e / c)) < math.log(1.6)).all() and ngram_lm.estimate(np.array([0]))[0] == 0


def test_toxicity_on_given_labels(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    found = toxicity.classify(docs, labels).join(labels, "doc_id").toPandas()
    assert found["score"].between(0, 1).all()
    held = found[found["held_out"]]
    assert ((held["predicted"] == 1) == (held["toxic"] == 1)).mean() > 0.9


def test_toxicity_without_labels(spark):
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    assert [r.score for r in toxicity.classify(frame(spark, ["x", None, ""]), labels).collect()] == [0.5] * 3
    assert toxicity.classify(frame(spark, []), labels).count() == 0


def test_quality_on_given_labels(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    found = quality.quality_posteriors(docs, labels).join(labels, "doc_id").toPandas()
    assert ((found["kept"]) == (found["quality"] == 1)).mean() > 0.95


def test_sites_shrink_towards_their_priors(spark):
    rows = [(i, "big" if i < 200 else f"small{i}", "p", 3.0 if i % 4 else -3.0) for i in range(210)]
    found = quality.posterior(spark.createDataFrame(rows, "doc_id long, _host string, _path string, _log_odds double"), 0.5).toPandas()
    big, small = found[found["_host"] == "big"], found[found["_host"] != "big"]
    assert big["_p_host"].nunique() == 1 and small["_p_host"].between(0.05, 0.95).all()
    assert abs(small["_p_host"] - big["_p_host"].iloc[0]).max() < 0.45  # single documents say 0.05 or 0.95
    empty = quality.quality_posteriors(frame(spark, [None, ""]), spark.createDataFrame([], "doc_id long, quality int"))
    assert empty.count() == 2
    assert [r[0] for r in spark.sql("SELECT 'https://A.example.com/en/825?x=1' AS u").select(*quality.url_levels(F.col("u"))).collect()] == ["a.example.com"]


def brute_posterior(rows, base_rate):
    """The posterior of (host, path, log odds) rows, recomputed with NumPy."""
    df = pd.DataFrame(rows, columns=["h", "q", "o"])
    df["p"] = 1 / (1 + np.exp(-df["o"]))

    def strength(t, prior):
        prior = prior + 0 * t["n"]
        noise, n, room = (prior * (1 - prior)).sum(), t["n"].sum(), (t["n"] * prior * (1 - prior)).sum()
        between = max(((t["n"] * (t["good"] / t["n"] - prior) ** 2).sum() - noise) / n, 1e-6)
        return min(max(room / n / between - 1, 1.0), 1e6)

    sums = {"n": ("p", "size"), "good": ("p", "sum")}
    hosts, paths = df.groupby("h", dropna=False).agg(**sums), df.groupby(["h", "q"], dropna=False).agg(**sums)
    prior = df["p"].mean()
    k = strength(hosts, prior)
    p_host = (hosts["good"] + k * prior) / (hosts["n"] + k)
    above = pd.Series(p_host.reindex(paths.index.get_level_values(0)).to_numpy(), paths.index)
    k = strength(paths, above)
    p_path = (paths["good"] + k * above) / (paths["n"] + k)
    rate = p_path.reindex(pd.MultiIndex.from_frame(df[["h", "q"]])).to_numpy()
    return 1 / (1 + np.exp(-(df["o"] - np.log(base_rate / (1 - base_rate)) + np.log(rate / (1 - rate)))))


def test_posteriors_against_numpy(spark):
    rng = random.Random(12)
    rows = [(rng.choice("aaaaabcd") + ("x" if rng.random() < 0.1 else ""), rng.choice("pqr"), rng.gauss(1, 3)) for _ in range(300)]
    df = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "doc_id long, _host string, _path string, _log_odds double").repartition(3)
    got = {r.doc_id: r._score for r in quality.posterior(df, 0.7).collect()}
    assert np.allclose([got[i] for i in range(len(rows))], brute_posterior(rows, 0.7), atol=1e-9)


def test_quality_of_edge_rows(spark):
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(60)], "doc_id long, quality int")
    texts = [("good plain words of a text " * 5 if i % 3 else "!!! ### $$$ WIN 99 $$$") + str(i) for i in range(60)]
    docs = frame(spark, [*texts, None, "", texts[1], texts[0], texts[1], "word " * 200_000], [*range(60), None, 61, 1, 1, None, 62])
    found = quality.quality_posteriors(docs.withColumn("_note", F.lit(1)), labels)
    assert found.count() == 66 and found.where("score IS NULL OR kept IS NULL").count() == 0
    kept = quality.keep_good(docs, labels)
    assert kept.columns == docs.columns
    rows = {(r.doc_id, r.text) for r in kept.collect()}
    assert (1, texts[1]) in rows and (1, texts[0]) not in rows and (None, texts[1]) in rows  # by row, not by id
    assert quality.quality_posteriors(docs.limit(0), labels).count() == 0 and quality.keep_good(docs.limit(0), labels).count() == 0


def test_chats_of_repeated_turns_and_long_conversations(spark):
    turns = [(1, i, "user", f"t{i}") for i in range(3000)] + [(2, i, "user", f"t{i}") for i in range(2999)] + [(3, 0, "user", "t0"), (3, 0, "user", "t0"), (4, 0, "user", "t0")]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    assert {r.conv_id: r.n_turns for r in chat.format_chats(df).collect()} == {1: 3000, 3: 2}


def test_chats_keep_maximal_conversations(spark):
    turns = [("user", "hi"), ("assistant", "hello"), ("user", "bye")]
    rows = []
    for conv, n in ((1, 1), (2, 2), (3, 3), (4, 3), (5, 2)):
        rows += [(conv, i, r, t, "d") for i, (r, t) in enumerate(turns[:n])]
    rows += [(6, 0, "user", "hi", "d"), (6, 1, "assistant", "other", "d"), (7, None, None, None, "d"), (None, 0, "user", "lost", "d")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, digest string")
    got = {r.conv_id: (r.n_turns, r.chat) for r in chat.format_chats(df).collect()}
    assert set(got) == {3, 6, 7}
    assert got[3][1] == "<|user|>\nhi<|end|>\n<|assistant|>\nhello<|end|>\n<|user|>\nbye<|end|>\n"
    assert got[7] == (1, "<|unknown|>\n<|end|>\n")
    assert chat.format_chats(df.limit(0)).count() == 0
