import hashlib
import re
import struct
import zlib

import corpus_pipeline
import numpy as np
import pytest
from featsift.llm import quality, suffix_dedup
from featsift.llm.queries import tokenizer_file
from test_dedup import brute_near, brute_spans
from test_models import brute_posterior

SF = "/root/testdata/sf0.001"


def good_ids(spark, rows):
    """The classifier's decisions, sites and posteriors recomputed with NumPy from the fitted weights."""
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    model = quality.fit(docs.select("doc_id", "text"), labels)
    odds = model.log_odds(np.array([quality.shape(r.text or "") for r in rows]))
    score = brute_posterior([(r.source, f"{r.source}/{r.lang}", o) for r, o in zip(rows, odds)], model.base_rate)
    return {r.doc_id for r, s in zip(rows, score) if s >= quality.KEEP}


@pytest.fixture(scope="module")
def expected(spark):
    """What every stage must keep, by brute force on all documents: rows after each stage."""
    rows = sorted(spark.read.parquet(f"{SF}/documents.parquet").collect(), key=lambda r: r.doc_id)
    good = good_ids(spark, rows)
    kept = [[r.asDict() for r in rows if r.doc_id in good]]
    first = {}
    for r in kept[-1]:
        first.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", r["text"] or ""), r)
    kept.append(list(first.values()))
    near = brute_near([r["text"] for r in kept[-1]])
    kept.append([r for i, (r, (_, c)) in enumerate(zip(kept[-1], near)) if c == i])
    cut = []
    for r, (_, _, _, left) in zip(kept[-1], brute_spans([r["text"] for r in kept[-1]])):
        text = left.decode("utf-8", "ignore")
        cut.append(r | {"text": text, "n_chars": len(text)})
    kept.append(cut)
    return kept


def test_stages_against_brute_force(spark, expected):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    assert len(expected[0]) < docs.count() and len(expected[1]) < len(expected[0])
    for (_, stage), want in zip(corpus_pipeline.STAGES[:-1], expected):
        docs = stage(spark, docs, SF).cache()
        assert docs.columns == columns
        assert sorted((r.asDict() for r in docs.collect()), key=lambda r: r["doc_id"]) == want


def test_run_packs_what_the_stages_keep(spark, expected):
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(tokenizer_file("byte_bpe_50k.json"))
    ids = {r["doc_id"]: [*tokenizer.encode(r["text"], add_special_tokens=False).ids, 0] for r in expected[-1]}
    cover = {i: np.zeros(len(v), int) for i, v in ids.items()}
    windows = {}
    for r in corpus_pipeline.run(spark, SF).collect():
        part = ids[r.doc_id][r.start : r.start + r.length]
        assert r.ids_crc32 == zlib.crc32(struct.pack(f"<{len(part)}I", *part)) and r.doc_tokens == len(ids[r.doc_id])
        cover[r.doc_id][r.start : r.start + r.length] += 1
        windows.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert all((c == 1).all() for c in cover.values())
    for pieces in windows.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 1024
    assert len(windows) <= sum(map(len, ids.values())) // 1024 + 3


def test_stages_of_nulls_repeats_and_nothing(spark):
    """Every stage handles null ids, texts, languages and sources, repeated ids and rows, and an empty table."""
    sample = spark.read.parquet(f"{SF}/documents.parquet")
    text = sample.where("lang = 'en'").orderBy("doc_id").first().text
    rows = [(1, text, "en", "a", 5), (1, text, "en", "a", 5), (1, "another text with the same id " + text[:50], "en", "a", 5), (None, text, None, None, None), (2, None, None, None, None), (3, "", "en", None, 0)]
    docs = spark.createDataFrame(rows, sample.schema)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, sample.limit(0), SF).count() == 0
        found = stage(spark, docs, SF)
        assert found.columns == sample.columns and found.count() <= len(rows)
        assert found.where("doc_id IS NULL").count() == 1
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, SF).collect()
    assert sum(r.start == 0 for r in pieces) == len(rows)
    assert corpus_pipeline.STAGES[-1][1](spark, sample.limit(0), SF).count() == 0


def test_cut_counts_maximal_runs():
    s = lambda a, b: a << 32 | b
    assert suffix_dedup.cut(b"0123456789", [s(2, 4), s(4, 6), s(8, 9)]) == (b"01679", 2)
    assert suffix_dedup.cut(b"0123456789", [s(0, 3), s(1, 2)]) == (b"3456789", 1)
    assert hashlib.sha256(suffix_dedup.cut(b"", [])[0]).hexdigest().startswith("e3b0")
