"""Nearest neighbours against brute force, and the pipeline's stages against plain versions."""

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from levelindex import scratch
from levelindex.llm import multi_index_hash as mih
from levelindex.llm import crf_toxicity, decontaminate, queries, suffix_dedup


def test_recall_and_scores(spark, sf):
    vectors = spark.read.parquet(f"{sf}/embeddings.parquet")
    p = vectors.toPandas()
    x, ids = np.stack(p.embedding).astype(float), p.vec_id.to_numpy()
    got = mih.nearest(vectors).toPandas()
    hit = total = 0
    for q, rows in got.groupby("query_id"):
        rows = rows.sort_values("rank")
        s = x @ x[np.flatnonzero(ids == q)[0]]
        s[ids == q] = -np.inf
        best = np.lexsort((ids, -s))[:20]
        hit += len(set(ids[best]) & set(rows.vec_id))
        total += 20
        assert rows["rank"].tolist() == list(range(1, 21)) and (np.diff(rows.score) <= 0).all()
        assert np.allclose(rows.score, [s[np.flatnonzero(ids == v)[0]] for v in rows.vec_id], atol=1e-12)
    assert set(got.query_id) == set(ids[ids % 20 == 0].tolist()) and hit / total >= 0.9
    exact = mih.nearest(vectors, exact=True).toPandas()
    assert len(exact) == len(got)


def test_probing_finds_every_code_within_the_radius():
    draw = np.random.default_rng(4)
    s = mih.HashSettings()
    codes = draw.integers(0, 1 << 63, 500, dtype=np.uint64)
    codes[100:200] = codes[:100] ^ np.uint64(0b1011)
    index = mih.MultiIndex(codes, s)
    for radius in (0, 3, 7, 10, 18):
        for q in codes[:20]:
            assert index.within(q, radius).tolist() == np.flatnonzero(np.bitwise_count(codes ^ q) <= radius).tolist()


def test_vector_cases(spark):
    rows = [(0, [1.0, 0.0]), (1, [0.0, 0.0]), (2, None), (3, [1.0, float("nan")]), (4, [0.5, 0.5]), (5, [0.5, 0.5]), (20, [0.2, 1.0]), (None, [1.0, 1.0]), (6, [1.0, None]), (7, [1.0, 2.0, 3.0])]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = sorted(tuple(r) for r in mih.nearest(v).collect())
    assert [r[:3] for r in got] == [(0, 1, 4), (0, 2, 5), (0, 3, 20), (20, 1, 4), (20, 2, 5), (20, 3, 0)]
    assert mih.nearest(v.limit(0)).count() == 0


def test_mixing_as_sql(spark, sf):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    ours = queries.QUERIES["op9_pfair_mix"](spark, sf).toPandas().sort_values("place")
    theirs = con.sql(queries.ORACLE_SQL["op9_pfair_mix"]).df().sort_values("place")
    assert (ours[["doc_id", "source", "block", "slot", "place"]].to_numpy() == theirs[["doc_id", "source", "block", "slot", "place"]].to_numpy()).all()


def plain_groups(texts: dict) -> set:
    """Least keys of the groups that a Jaccard of 0.8 over sets of five words links, by all pairs."""
    sets = {}
    for k, t in texts.items():
        words = (t or "").lower().split()
        sets[k] = frozenset(" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))) if words else frozenset()
    keys = sorted(sets)
    root = {k: k for k in keys}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i, a in enumerate(keys):
        for b in keys[i + 1 :]:
            both = len(sets[a] & sets[b])
            if 9 * both >= 4 * (len(sets[a]) + len(sets[b])):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {find(k) for k in keys}


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = docs.columns
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        before = docs
        docs = scratch.save(stage(spark, docs, sf), name)
        kept[name] = (before, docs)
        if name != "mix_sources":
            assert docs.columns == names
            assert docs.where("n_chars != length(text)").count() == 0 or name in ("toxicity", "simhash_near_dedup")
    before, after = kept["toxicity"]
    toxic = {r.doc_id for r in crf_toxicity.toxicity_scores(before, spark.read.parquet(f"{sf}/labels.parquet")).where("predicted = 1").collect()}
    assert {r.doc_id for r in after.collect()} == {r.doc_id for r in before.collect()} - toxic
    before, after = kept["simhash_near_dedup"]
    assert {r.doc_id for r in after.collect()} == plain_groups({r.doc_id: r.text for r in before.collect()})
    before, after = kept["benchmark_decontamination"]
    found = {r.doc_id for r in decontaminate.leaks(before, spark.read.parquet(f"{sf}/benchmark.parquet")).collect()}
    assert {r.doc_id for r in after.collect()} == {r.doc_id for r in before.collect()} - found
    before, after = kept["suffix_array_dedup"]
    assert after.count() == before.count()
    cut = {r.doc_id: r.n_removed for r in suffix_dedup.repeated_bytes(before).collect()}
    left = {r.doc_id: len(r.text.encode()) for r in after.collect()}
    for r in before.collect():  # whole characters: at most three bytes more stay at each end of a cut
        assert 0 <= left[r.doc_id] - (len(r.text.encode()) - cut[r.doc_id]) <= (60 if cut[r.doc_id] else 0)
    before, after = kept["mix_sources"]
    assert {r.doc_id for r in after.collect()} == {r.doc_id for r in before.collect()}
    assert corpus_pipeline.run(spark, sf).count() == after.count()


@pytest.mark.parametrize("rows", [[], [(1, None, None, None, None), (1, "x y", "en", "s", 3), (1, "x y", "en", "s", 3), (None, "a b", None, None, 3)]])
def test_stage_cases(spark, sf, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES:
        docs = scratch.save(stage(spark, docs, sf), name)
    assert docs.count() == (3 if rows else 0)


def test_stages_take_any_further_columns(spark, sf):
    names = ["__id", "__row", "__n", "begins", "ends", "key", "row", "n", "own", "m", "start", "offset", "block", "frames", "turn", "mix_source", "slot", "at", "a.b"]
    fields = ", ".join(f"`{n}` string" for n in names)
    docs = spark.createDataFrame([(i, f"text number {i} of some words", "en", f"s{i % 2}", 10, *map(str, range(len(names))), {"k": i}) for i in range(6)], f"doc_id long, text string, lang string, source string, n_chars long, {fields}, more map<string,int>")
    before = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        docs = scratch.save(stage(spark, docs, sf), name)
        assert docs.columns[: len(before)] == before
    assert docs.count() == 6 and {"_block", "_slot", "place"} <= set(docs.columns)
    assert {tuple(r[n] for n in names) for r in docs.collect()} == {tuple(map(str, range(len(names))))}


def test_cuts_keep_characters_whole():
    raw = "aé日b".encode()
    assert corpus_pipeline.whole_characters(raw, [2], [5]) == "aé日b"[0:2] + "日b"
    assert corpus_pipeline.whole_characters(raw, [1], [6]) == "ab"
    assert corpus_pipeline.whole_characters(raw, [], []) == "aé日b"
