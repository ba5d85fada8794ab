import hashlib
import random
import re
from fractions import Fraction

import numpy as np
import pytest

from featsift.llm import components, exact_dedup, minhash_dedup, suffix_dedup
from featsift.llm.components import connected_components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, component string, span string, bucket string"


def frame(spark, texts, ids=None):
    ids = range(len(texts)) if ids is None else ids
    return spark.createDataFrame([(i, t, None, "s", None, "k", "c", "x", "b") for i, t in zip(ids, texts)], SCHEMA)


def brute_spans(texts):
    seen, out = {}, []
    for text in texts:
        data = (text or "").encode()
        gone = np.zeros(len(data), bool)
        for p in range(len(data) - 99):
            s = data[p : p + 100]
            if s in seen:
                gone[p : p + 100] = True
            else:
                seen[s] = True
        kept = bytes(b for b, g in zip(data, gone) if not g)
        out.append((len(data), int(gone.sum()), int((np.diff(np.concatenate(([0], gone.astype(int)))) == 1).sum()), kept))
    return out


def corpus(seed, n=60):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choices("abcdefgh é", k=rng.randint(1, 9)))
    prose = lambda k: " ".join(word() for _ in range(k))
    passages = [prose(rng.randint(15, 40)) for _ in range(5)]
    texts = []
    for i in range(n):
        kind = i % 8
        if kind == 0 and texts:
            t = rng.choice(texts)
        elif kind == 1 and texts and (t := rng.choice(texts)):
            for _ in range(rng.randint(1, 4)):
                at = rng.randrange(len(t) + 1)
                t = t[:at] + rng.choice("xyz") + t[at + rng.randint(0, 2) :]
        elif kind == 2:
            t = "a" * rng.randint(90, 400)
        elif kind == 3:
            t = "ab \n" * rng.randint(20, 90)
        elif kind == 4:
            p = rng.choice(passages)
            a = rng.randrange(20)
            t = prose(10) + p[a : len(p) - rng.randrange(20)] + prose(5)
        elif kind == 5:
            t = rng.choice(["", "x", "b" * 99, "b" * 100, "b" * 101])
        elif kind == 6:
            p = rng.choice(passages)
            t = p + p + prose(3) + p[:110]
        else:
            t = prose(rng.randint(0, 120))
        texts.append(t)
    return texts


@pytest.mark.parametrize("seed", [1, 2])
def test_repeats_against_brute_force(spark, seed):
    texts = corpus(seed) + [None, "q" * 5000]
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in suffix_dedup.remove_repeats(frame(spark, texts).repartition(5)).collect()}
    want = brute_spans(texts)
    assert [got[i] for i in range(len(texts))] == want


def test_repeats_names_in_several_bitmaps(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "FILTER_BYTES", 128)
    texts = corpus(3)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in suffix_dedup.remove_repeats(frame(spark, texts).repartition(3)).collect()}
    assert [got[i] for i in range(len(texts))] == brute_spans(texts)


def test_repeats_with_often_repeated_names_split(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "HOT_LEAST", 2)
    rng = random.Random(9)
    line = "a line of seventy bytes that stands in every text, between other words"
    texts = [f"{rng.random()} {line[rng.randrange(3):]} {rng.choice('xyz') * rng.randrange(4)}{rng.random() if i % 5 else ' and the same words follow it here again'}" for i in range(60)]
    texts += corpus(6, 24)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in suffix_dedup.remove_repeats(frame(spark, texts).repartition(3)).collect()}
    assert [got[i] for i in range(len(texts))] == brute_spans(texts)


def test_cover_has_a_common_distance_for_any_two_positions():
    period, cover = suffix_dedup.PERIOD, set(suffix_dedup.COVER)
    for a in range(period):
        for b in range(period):
            assert any((a + d) % period in cover and (b + d) % period in cover for d in range(period))
    assert suffix_dedup.NAME + period - 1 == suffix_dedup.LENGTH


def test_samples_stand_where_the_phase_says():
    docs, texts = np.array([4, 900], np.int64), [bytes(range(32, 127)) * 3, b"xyz" * 70]
    raw = suffix_dedup.PAD + b"".join(t + suffix_dedup.PAD for t in texts)
    starts = np.array([104, 208 + len(texts[0])])
    at, which, name, _ = suffix_dedup.samples(docs, starts, np.array([len(t) for t in texts]), raw)
    for k, t in enumerate(texts):
        want = [p for p in range(len(t) - suffix_dedup.NAME + 1) if (p + suffix_dedup.phase(docs)[k]) % suffix_dedup.PERIOD in suffix_dedup.COVER]
        assert (at[which == k] - starts[k]).tolist() == want
        tuples = [t[p : p + suffix_dedup.NAME] for p in want]
        assert len(set(name[which == k].tolist())) == len(set(tuples))


def test_bytes_decide_where_hashes_collide():
    rows = np.frombuffer(b"abcabdabcabe", np.uint8).reshape(4, 3)
    order, head = suffix_dedup._sorted_equal(np.zeros(4, np.uint64), rows)
    groups = {}
    for place, row in enumerate(order.tolist()):
        groups.setdefault(int(order[head[place]]), set()).add(row)
    assert groups == {0: {0, 2}, 1: {1}, 3: {3}}


def test_repeats_of_repeated_rows_null_ids_and_empty(spark):
    t = corpus(4)[7] + "z" * 20
    rows = frame(spark, [t, t, t, None], [3, 3, None, 4])
    assert sorted((r.doc_id or 0, r.n_removed) for r in suffix_dedup.remove_repeats(rows).collect()) == [(0, 0), (3, 0), (3, 0), (4, 0)]
    assert suffix_dedup.remove_repeats(frame(spark, [])).count() == 0


def brute_near(texts):
    sets = []
    for t in texts:
        w = minhash_dedup.words_of(t or "")
        n = min(5, len(w))
        sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set())
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return [(len(s), find(i)) for i, s in enumerate(sets)]


def near_corpus(seed):
    rng = random.Random(seed)
    bases = [[f"w{rng.randrange(500)}" for _ in range(rng.choice([3, 5, 40, 200]))] for _ in range(12)]
    texts = []
    for _ in range(150):
        words = list(rng.choice(bases))
        for _ in range(rng.choice([0, 0, 1, 2, len(words) // 40, len(words) // 25])):
            words[rng.randrange(len(words))] = f"x{rng.randrange(9999)}"
        texts.append(rng.choice([" ", "\n", " \t "]).join(w.upper() if rng.random() < 0.1 else w for w in words))
    return texts + [None, "", "  \n", "one", "ONE", "a b c d", "é É"]


@pytest.mark.parametrize("block_bytes", [2 << 20, 6_000])
def test_near_duplicates_against_brute_force(spark, monkeypatch, block_bytes):
    monkeypatch.setattr(minhash_dedup.verified_links, "__defaults__", (block_bytes,))
    texts = near_corpus(5)
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash_dedup.near_duplicates(frame(spark, texts).repartition(4)).collect()}
    assert [got[i] for i in range(len(texts))] == [(n, c, c == i) for i, (n, c) in enumerate(brute_near(texts))]


def test_near_copies_in_one_large_group_and_bridges_between_blocks(spark, monkeypatch):
    """Many near copies of one text, texts that only one of them is similar to, and two looser groups."""
    monkeypatch.setattr(minhash_dedup.verified_links, "__defaults__", (8_000,))
    rng = random.Random(4)
    base = [f"w{i}" for i in range(60)]
    texts = []
    for i in range(80):
        words = list(base)
        words[rng.randrange(60)] = f"x{i}"
        texts.append(" ".join(words))
    drift = list(base)
    for i in range(30):  # a chain that leaves the group step by step
        drift[i] = f"d{i}"
        texts.append(" ".join(drift))
    rng.shuffle(texts)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash_dedup.near_duplicates(frame(spark, texts).repartition(3)).collect()}
    assert [got[i] for i in range(len(texts))] == brute_near(texts)


def test_near_duplicates_edge_rows(spark):
    rows = frame(spark, ["a b c d e f", "a b c d e f", None, "a b c d e f", "g"], [7, 7, 8, None, None])
    got = sorted(((r.doc_id, r.component_id, r.kept) for r in minhash_dedup.near_duplicates(rows).collect()), key=str)
    assert got == [(7, 7, True), (7, 7, True), (8, 8, True), (None, None, True), (None, None, True)]
    assert minhash_dedup.near_duplicates(frame(spark, [])).count() == 0


def test_pruning_keeps_pairs_at_the_threshold():
    assert minhash_dedup.least_matches(252, 0.75) < 160
    assert minhash_dedup.similar(np.arange(75, dtype=np.uint64), np.arange(100, dtype=np.uint64), Fraction(3, 4))
    assert not minhash_dedup.similar(np.arange(74, dtype=np.uint64), np.arange(100, dtype=np.uint64), Fraction(3, 4))


@pytest.mark.parametrize("at_once", [500_000, 30])
def test_components_of_chains_and_stars(spark, monkeypatch, at_once):
    """In one task, and with rounds over many."""
    monkeypatch.setattr(components, "EDGES_AT_ONCE", at_once)
    edges = [(i, i + 1) for i in range(10, 60)] + [(100, x) for x in range(101, 150)] + [(7, 7), (None, 3), (150, 149), (149, 150)]
    got = dict(connected_components(spark.createDataFrame(edges, "u long, v long")).collect())
    assert got == {i: 10 for i in range(10, 61)} | {i: 100 for i in range(100, 151)}
    assert connected_components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_stars_of_random_edges():
    rng = np.random.default_rng(5)
    for n in (1, 30, 400):
        u, v = rng.integers(-n, n, n), rng.integers(-n, n, n)
        root = {i: i for i in {*u.tolist(), *v.tolist()}}

        def find(i):
            while root[i] != i:
                i = root[i]
            return i

        for a, b in zip(u.tolist(), v.tolist()):
            a, b = sorted((find(a), find(b)))
            root[b] = a
        got = dict(zip(*(x.tolist() for x in components.stars_of(u, v))))
        assert got == {i: find(i) for i in root if find(i) != i}


def brute_exact(texts, ids):
    groups = {}
    for i, t in zip(ids, texts):
        groups.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", t or ""), []).append(i)
    least = {t: min((i for i in g if i is not None), default=None) for t, g in groups.items()}
    out = []
    for i, t in zip(ids, texts):
        n = re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
        out.append((i, least[n], len(groups[n]), i == least[n], hashlib.sha256(n.encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize(("key_bits", "capacity"), [(64, 1), (64, 1000), (4, 1), (1, 1000)])
def test_exact_duplicates(spark, key_bits, capacity):
    """Fewer key bits make chains of different texts, which only their bytes tell apart."""
    rng = random.Random(3)
    texts = ["a  b", "a b", "a\t\n b", "A b", None, "", " ", "é", "a b", "x" * 20_000, "x" * 20_000 + "y"] + ["hot\n text"] * 40 + [f"t {rng.randrange(25)}" for _ in range(60)]
    ids = [*range(len(texts))]
    ids[30:33] = [None, None, 7]  # null and repeated ids
    ids[-1] = ids[-2]
    found = exact_dedup.exact_duplicates(frame(spark, texts, ids).repartition(3), capacity=capacity, key_bits=key_bits)
    assert sorted((tuple(r) for r in found.select("doc_id", "keep_id", "group_size", "kept", "text_sha256").collect()), key=str) == brute_exact(texts, ids)


def test_exact_duplicates_of_nothing(spark):
    assert exact_dedup.exact_duplicates(frame(spark, [])).count() == 0
    assert exact_dedup.drop_exact_duplicates(frame(spark, [])).count() == 0
    kept = exact_dedup.drop_exact_duplicates(frame(spark, ["x", "x", "x"], [5, 4, None]))
    assert sorted(str(r.doc_id) for r in kept.collect()) == ["4", "None"]


@pytest.mark.parametrize("look", [16, 3])
def test_directory_doubles_only_overfull_buckets(spark, monkeypatch, look):
    monkeypatch.setattr(exact_dedup, "LOOK_BITS", look)
    keys = spark.range(2000).selectExpr("CASE WHEN id < 1500 THEN xxhash64(id) ELSE shiftrightunsigned(xxhash64(id), 9) END AS key").distinct()
    buckets = exact_dedup.directory(keys, 70)
    assert len({d for d, _ in buckets}) > 1
    assert sum(2.0**-d for d, _ in buckets) == 1.0  # the ranges cover all keys once
    placed = exact_dedup.with_bucket(keys, buckets).groupBy("bucket").count().collect()
    assert sum(r["count"] for r in placed) == 2000 and max(r["count"] for r in placed) <= 70
    assert exact_dedup.directory(keys, 5000) == [(0, 0)]
    assert exact_dedup.directory(keys.limit(0), 1) == [(0, 0)]
