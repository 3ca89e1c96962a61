"""Texts longer than any inner block, against plain versions."""

from __future__ import annotations

import random

import numpy as np
import pytest
import xxhash

from pyspark.sql import functions as F

from levelindex.llm import hmm_lm, mil_quality, multi_index_hash, simhash_gray


def plain_fingerprint(text: bytes, n: int) -> int:
    words = text.lower().split()
    grams = [b" ".join(words[i : i + n]) for i in range(len(words) - n + 1)]
    h = np.array([xxhash.xxh64_intdigest(g, 42) for g in grams], np.uint64)
    return sum(1 << i for i in range(64) if 2 * int(((h >> np.uint64(i)) & np.uint64(1)).sum()) > len(h))


@pytest.mark.parametrize("shingles", [131_071, 131_072, 131_073, 131_600, 300_000])
def test_no_shingle_of_a_long_text_is_lost(shingles):
    draw = random.Random(shingles)
    text = " ".join(f"w{draw.randrange(40)}" for _ in range(shingles + 3)).encode()
    assert simhash_gray.fingerprint(text) == plain_fingerprint(text, 4)


def test_fingerprint_at_any_block_size(monkeypatch):
    monkeypatch.setattr(simhash_gray, "SHINGLES_AT_ONCE", 7)
    draw = random.Random(2)
    for n in range(5, 60):
        text = " ".join(f"w{draw.randrange(9)}" for _ in range(n)).encode()
        assert simhash_gray.fingerprint(text) == plain_fingerprint(text, 4)


def test_deep_gray_tree_finds_all_pairs():
    draw = np.random.default_rng(3)
    base = draw.integers(0, 1 << 63, 700, dtype=np.uint64)
    flips = [base ^ np.uint64(1 << int(a)) ^ np.uint64(1 << int(b)) for a, b in draw.integers(0, 64, (60, 2))]
    fps = np.unique(np.concatenate([base, *flips]))
    index = simhash_gray.GrayIndex(fps, 13)
    assert len(index.levels) == 3
    q, m = index.near(index.fp[:300], 4, 0)
    want = np.bitwise_count(index.fp[:300, None] ^ index.fp[None]) <= 4
    assert set(zip(q.tolist(), m.tolist())) == set(zip(*(x.tolist() for x in np.nonzero(want))))


def test_codes_take_the_largest_finite_numbers(spark):
    rows = [(i, [float(i % 7) + 1, 2.0, -1.0]) for i in range(60)] + [(100, [1e305, 1e305, 0.0]), (101, [float("inf"), 0.0, 1.0])]
    found = multi_index_hash.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), k=3).collect()
    assert {r.vec_id for r in found if r["rank"] == 1 and r.query_id != 100} == {100}
    assert not any(101 in (r.query_id, r.vec_id) for r in found)


def test_quality_features_do_not_depend_on_neighbours_or_groups():
    s = mil_quality.MilSettings(passage_bytes=64, group=4)
    draw = random.Random(5)
    texts = [" ".join("".join(draw.choices("abcdeé ", k=draw.randrange(1, 9))) for _ in range(n)).encode() for n in (0, 1, 7, 40, 300, 2000)]
    raw = [np.frombuffer(t, np.uint8) for t in texts]
    together, sizes = mil_quality.encode_passages(raw, 64)
    ends = np.cumsum(sizes)
    for t, a, b in zip(raw, ends - sizes, ends):
        known = mil_quality.text_features(t, 64, 4)
        pieces = [mil_quality.encode_passages([t[i : i + 256]], 64, known)[0] for i in range(0, max(len(t), 1), 256)]
        assert np.allclose(together[a:b], np.concatenate(pieces), atol=1e-6)
        assert np.allclose(together[a:b], mil_quality.encode_passages([t], 64)[0], atol=1e-6)


def test_quality_scores_are_the_same_for_every_partitioning(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    found = []
    for n in (1, 7):
        rows = mil_quality.quality_scores(docs.repartition(n), labels).collect()
        found.append({r.doc_id: r.score for r in rows})
    assert found[0].keys() == found[1].keys()
    assert max(abs(found[0][k] - found[1][k]) for k in found[0]) < 1e-4


def test_gradients_of_a_long_text_are_those_of_the_whole():
    s = mil_quality.MilSettings(passage_bytes=32, group=3)
    raw = np.frombuffer(" ".join(f"word{i % 17}" for i in range(200)).encode(), np.uint8)
    x, sizes = mil_quality.encode_passages([raw], 32)
    model = mil_quality.AttentionMil.fresh(s, x.mean(axis=0), x.std(axis=0) + 0.01)
    whole = model.gradients((x - model.mean) / model.spread, sizes, np.array([1.0]), 5)
    pieces = model.long_gradients(raw, 1.0, 5, s)
    assert all(np.allclose(whole[k], pieces[k], atol=1e-6) for k in whole)


def test_expected_counts_carry_over_runs():
    draw = np.random.default_rng(4)
    model = hmm_lm.Hmm.initial(np.full(30, 1 / 30), 4, 1)
    blobs = [draw.integers(0, 30, n).astype(np.uint16).tobytes() for n in (1, 5, 23, 64, 7, 50)]
    whole = model.expect(*hmm_lm.runs_of(blobs, 1000))
    for length in (1, 5, 7, 64):
        cut = model.expect(*hmm_lm.runs_of(blobs, length))
        assert all(np.allclose(whole[k], cut[k], rtol=1e-9, atol=1e-12) for k in whole)


def test_language_model_learns_nothing_from_held_out_texts(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    held = F.crc32(F.col("doc_id").cast("string")) % 5 == 1
    other = docs.withColumn("text", F.when(held, F.lit("entirely other words words words")).otherwise(F.col("text")))
    a, b = ({r.doc_id: (r.score, r.base_score) for r in hmm_lm.hmm_scores(x).where(~F.col("held_out")).collect()} for x in (docs, other))
    assert a.keys() == b.keys() and all(np.allclose(a[k], b[k], rtol=1e-9) for k in a)
