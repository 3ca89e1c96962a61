"""Operators on texts: against plain versions, and the cases that each docstring defines."""

import collections
import hashlib
import math
import random

import numpy as np
import pytest
import xxhash

from levelindex.llm import crf_toxicity, decontaminate, hmm_lm, html_main_text, mil_quality, pfair_mix, simhash_gray, suffix_blocks, suffix_dedup, token_counts
from levelindex.llm.common import LOWER_TABLE

DOCS = "doc_id long, text string, source string, score double, fp long, row long, part int"


def documents(spark, rows):
    """Rows of (key, text) with other columns whose names clash with the operators' own."""
    return spark.createDataFrame([(k, t, "s" if k is None else f"s{k % 3}", 0.5, 1, 2, 3) for k, t in rows], DOCS)


ODD = [(1, None), (2, ""), (3, " \n\t "), (None, "a text without a key"), (4, "same text here and there"), (5, "same text here and there"), (5, "same text here and there"), (6, "word " * 30000), (7, "é à ü 日本 😀 <|endoftext|> x")]


@pytest.fixture(scope="module")
def odd(spark):
    return documents(spark, ODD).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return documents(spark, [])


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(k, k % 2, k % 2) for k in range(10)] + [(11, None, None)], "doc_id long, quality int, toxic int")


# --- token counts ---

def test_token_counts_as_the_library(spark, sf):
    import public_tokenizers
    import tokenizers

    library = tokenizers.Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    random.seed(2)
    texts = [t for _, t in ODD if t is not None] + ["".join(random.choice("ab \n\té'12! 　\x1c") for _ in range(random.randint(1, 40))) for _ in range(400)]
    own = token_counts.counter(token_counts.vocabulary_path())
    for t in texts:
        assert own.count(t) == len(library.encode(t, add_special_tokens=False).ids), t[:60]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for r, t in zip(token_counts.token_counts(docs).orderBy("doc_id").collect(), docs.orderBy("doc_id").collect()):
        assert r.n_tokens == len(library.encode(t.text, add_special_tokens=False).ids)
        assert r.n_bytes == len(t.text.encode()) and r.over_limit == (r.n_tokens > 1024)


def test_token_counts_cases(odd, empty):
    rows = token_counts.token_counts(odd).collect()
    assert len(rows) == len(ODD)
    assert all(r.n_tokens == 0 for r in rows if r.doc_id in (1, 2))
    assert token_counts.token_counts(empty).count() == 0


# --- language model ---

def test_hmm_base_score_and_probability(spark, sf):
    import zlib

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {r.doc_id: r for r in hmm_lm.hmm_scores(docs).collect()}
    words = {r.doc_id: r.text.encode().translate(LOWER_TABLE).split() for r in docs.collect()}
    held = {k: zlib.crc32(str(k).encode()) % 5 == 1 for k in words}
    counts = collections.Counter()
    for k, w in words.items():
        if not held[k]:
            counts.update([*w, None])
    n, v = sum(counts.values()), len(counts)
    for k, w in words.items():
        base = sum(math.log10((counts[x] + 0.5) / (n + 0.5 * (v + 1))) for x in [*w, None])
        assert got[k].base_score == pytest.approx(base, rel=1e-9)
        assert (got[k].n_tokens, got[k].n_known, got[k].train_tokens, got[k].held_out) == (len(w) + 1, sum(counts[x] > 0 for x in [*w, None]), n, held[k])
    out = [r for r in got.values() if r.held_out]
    assert sum(r.score for r in out) > sum(r.base_score for r in out)


def test_forward_is_exact_and_rounds_raise_the_likelihood():
    draw = np.random.default_rng(1)
    model = hmm_lm.Hmm.initial(np.full(6, 1 / 6), 3, 4)
    seqs = [draw.integers(0, 6, n).astype(np.uint16) for n in (1, 5, 9, 2, 40)]
    plain = []
    for s in seqs:
        a = model.start * model.emit[:, s[0]]
        for x in s[1:]:
            a = (a @ model.move) * model.emit[:, x]
        plain.append(np.log10(a.sum()))
    assert np.allclose(model.forward(seqs), plain)
    total = [model.forward(seqs).sum()]
    for _ in range(5):
        model = model.updated(model.expect(seqs, np.ones(5, bool)), 0.0)
        total.append(model.forward(seqs).sum())
    assert total[-1] > total[0]
    # all sequences of two symbols have probability one together
    pairs = [np.array([a, b], np.uint16) for a in range(6) for b in range(6)]
    assert (10 ** model.forward(pairs)).sum() == pytest.approx(1)


def test_hmm_cases(odd, empty):
    rows = hmm_lm.hmm_scores(odd, hmm_lm.HmmSettings(rounds=1, warm_rounds=2)).collect()
    assert len(rows) == len(ODD) and all(math.isfinite(r.score) for r in rows)
    assert all(r.n_tokens == 1 for r in rows if r.doc_id in (1, 2, 3)) and all(r.held_out for r in rows if r.doc_id is None)
    assert hmm_lm.hmm_scores(empty).count() == 0


# --- quality and toxicity ---

def test_quality_learns_from_document_labels():
    random.seed(4)
    good = [" ".join(random.choice(["the", "of", "stone", "river", "walks", "green"]) for _ in range(80)) for _ in range(150)]
    bad = ["%%% ".join(random.choice(["BUY", "NOW", "CLICK"]) for _ in range(80)) for _ in range(150)]
    model = mil_quality.fit([t.encode() for t in good[:100] + bad[:100]], [1] * 100 + [0] * 100, mil_quality.MilSettings(epochs=4))
    score = model.score_many([np.frombuffer(t.encode(), np.uint8) for t in good[100:] + bad[100:]], mil_quality.MilSettings())
    assert score[:50].min() > 0.5 > score[50:].max()


def test_attention_gradient_and_long_texts():
    s = mil_quality.MilSettings(hidden=3, attention=2, group=4)
    draw = np.random.default_rng(2)
    model = mil_quality.AttentionMil.fresh(s, np.zeros(mil_quality.WIDTH), np.ones(mil_quality.WIDTH))
    x, sizes, y = draw.normal(size=(5, mil_quality.WIDTH)) * 0.1, np.array([2, 3]), np.array([1.0, 0.0])

    def loss():
        h = np.tanh(x @ model.p["w"] + model.p["b"])
        a = (np.tanh(h @ model.p["v"]) / (1 + np.exp(-(h @ model.p["u"])))) @ model.p["a"]
        total, at = 0, 0
        for n, t in zip(sizes, y):
            e = np.exp(a[at : at + n])
            p = 1 / (1 + np.exp(-(e @ h[at : at + n] / e.sum() @ model.p["c"] + model.p["d"][0])))
            total -= t * np.log(p) + (1 - t) * np.log(1 - p)
            at += n
        return total / 2

    grads = model.gradients(x, sizes, y)
    for name in model.NAMES:
        flat, g = model.p[name].ravel(), grads[name].ravel()
        for i in (0, len(flat) - 1):
            keep, eps = flat[i], 1e-5
            flat[i] = keep + eps
            up = loss()
            flat[i] = keep - eps
            down = loss()
            flat[i] = keep
            assert (up - down) / (2 * eps) == pytest.approx(g[i], abs=1e-6), name
    model.ready()
    assert 0 <= model.score(np.frombuffer(b"long text " * 3000, np.uint8), s) <= 1


def test_toxicity_finds_words_and_offsets(spark):
    random.seed(6)
    plain = ["".join(random.choice("aeioustrnl") for _ in range(6)) for _ in range(2000)]
    text = lambda toxic: " ".join(random.choice(plain) for _ in range(30)) + (" you blorg, " + random.choice(plain) if toxic else "")
    rows = [(i, text(i % 3 == 0)) for i in range(600)]
    docs = documents(spark, rows)
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(600)], "doc_id long, toxic int")
    got = crf_toxicity.toxicity_scores(docs, labels).collect()
    assert all(r.predicted == int(r.doc_id % 3 == 0) for r in got)
    for r in got:
        if r.predicted:
            assert any("blorg" in rows[r.doc_id][1][s.begin : s.end] for s in r.spans)


def test_chain_marginals_are_exact():
    draw = np.random.default_rng(3)
    move, start = np.array([[0.9, 0.1], [0.4, 0.6]]), np.array([0.8, 0.2])
    chain = crf_toxicity.Chain({}, 0.0, move, start, np.zeros(4))
    sizes = [1, 3, 200, 7]
    e = draw.normal(size=sum(sizes))
    starts = np.zeros(len(e), bool)
    starts[np.cumsum(sizes) - sizes] = True
    got, at = chain.marginals(e, starts), 0
    for n in sizes:
        g = np.stack([np.ones(n), np.exp(e[at : at + n])], axis=1)
        f = [start * g[0]]
        for i in range(1, n):
            f.append((f[-1] @ move) * g[i])
        b = [np.ones(2)]
        for i in range(n - 1, 0, -1):
            b.append(move @ (g[i] * b[-1]))
        both = np.array(f) * np.array(b[::-1])
        assert np.allclose(got[at : at + n], both[:, 1] / both.sum(axis=1))
        at += n


def test_classifier_cases(spark, odd, empty, labels):
    none = labels.limit(0)
    for f in (mil_quality.quality_scores, crf_toxicity.toxicity_scores):
        for known in (labels, none):
            rows = f(odd, known).collect()
            assert len(rows) == len(ODD) and all(0 <= r.score <= 1 for r in rows)
            assert all(r.held_out for r in rows if r.doc_id is None)
            assert f(empty, known).count() == 0


# --- suffix deduplication ---

def repeated_plain(docs, least=50):
    first = {}
    for k, t in sorted(docs, key=lambda x: x[0]):
        for i in range(len(t) - least + 1):
            first.setdefault(t[i : i + least], k)
    out = []
    for k, t in docs:
        gone = bytearray(len(t))
        for i in range(len(t) - least + 1):
            if first[t[i : i + least]] < k:
                gone[i : i + least] = b"\1" * least
        spans = sum(1 for i in range(len(t)) if gone[i] and (not i or not gone[i - 1]))
        out.append((k, len(t), sum(gone), spans, hashlib.sha256(bytes(b for b, g in zip(t, gone) if not g)).hexdigest()))
    return sorted(out)


def test_suffix_dedup_as_brute_force(spark, monkeypatch):
    random.seed(5)
    words = ["".join(random.choice("abcé") for _ in range(random.randint(1, 6))) for _ in range(30)]
    passages = [" ".join(random.choice(words) for _ in range(25)) for _ in range(6)]
    docs = []
    for i in range(200):
        parts = [random.choice(passages)[random.randint(0, 30) : random.randint(40, 140)] if random.random() < 0.5 else " ".join(random.choice(words) for _ in range(random.randint(0, 30))) for _ in range(random.randint(0, 5))]
        docs.append((i, " ".join(parts) if random.random() < 0.9 else "ab" * 100))
    docs += [(17, docs[17][1]), (18, "other row of a key " * 9)]
    monkeypatch.setattr(suffix_dedup, "BLOCK_BYTES", 3000)
    monkeypatch.setattr(suffix_dedup, "PART_BYTES", 2000)
    got = suffix_dedup.repeated_bytes(documents(spark, docs)).collect()
    assert sorted(tuple(r) for r in got) == repeated_plain([(k, t.encode()) for k, t in docs])


def test_long_texts_are_scanned_in_pieces(monkeypatch):
    random.seed(8)
    text = bytes(random.choice(b"abcd ") for _ in range(5000))
    whole = suffix_dedup.Runs([text], 50)
    monkeypatch.setattr(suffix_dedup, "PIECE", 700)
    parts = suffix_dedup.Runs([text], 50)
    cover = lambda r: sorted((s + i, int(a)) for s, c, a in zip(r.start, r.count, r.anchor) for i in range(c))
    assert cover(whole) == cover(parts)


def test_suffix_dedup_cases(odd, empty):
    rows = suffix_dedup.repeated_bytes(odd).collect()
    assert len(rows) == len(ODD)
    assert all(r.n_removed == 0 for r in rows if r.doc_id is None or r.doc_id <= 4)
    assert suffix_dedup.repeated_bytes(empty).count() == 0


def test_suffix_arrays():
    random.seed(3)
    for _ in range(150):
        letters = random.choice([b"a", b"ab", b"abc", bytes(range(256))])
        s = bytes(random.choice(letters) for _ in range(random.randint(0, 200)))
        s = s[:20] * 8 if random.random() < 0.4 else s
        assert suffix_blocks.suffix_array(s, random.choice([5, 50, 1000])).tolist() == sorted(range(len(s)), key=lambda i: s[i:])


# --- SimHash ---

def fingerprint_plain(text):
    w = text.encode().translate(LOWER_TABLE).split()
    shingles = [b" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or ([b" ".join(w)] if w else [])
    votes = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s, 42)
        for i in range(64):
            votes[i] += h >> i & 1
    return sum(1 << i for i in range(64) if 2 * votes[i] > len(shingles))


def components_plain(fps):
    parent = list(range(len(fps)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(fps)):
        for j in np.flatnonzero(np.bitwise_count(fps ^ fps[i]) <= 4):
            parent[find(i)] = find(int(j))
    return [find(i) for i in range(len(fps))]


def test_simhash_as_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").toPandas()
    fps = np.array([fingerprint_plain(t) for t in docs.text], np.uint64)
    docs["c"] = components_plain(fps)
    least = docs.groupby("c").doc_id.transform("min")
    got = {r.doc_id: r for r in simhash_gray.near_duplicates(spark.read.parquet(f"{sf}/documents.parquet")).collect()}
    for k, f, c in zip(docs.doc_id, fps, least):
        assert got[k].fingerprint == f"{f:016x}" and got[k].component_id == c


def test_forest_joins_what_all_links_join():
    draw = np.random.default_rng(1)
    fps = [int(x) for x in draw.integers(0, 1 << 63, 150, dtype=np.uint64)]
    for x in fps[:60]:
        for _ in range(15):
            for b in draw.choice(64, draw.integers(1, 8), replace=False):
                x ^= 1 << int(b)
            fps.append(x)
    fps = np.unique(np.array(fps, np.uint64))
    a, b = simhash_gray.forest(fps, 4, 13)
    at = {int(x): i for i, x in enumerate(fps)}
    label = list(range(len(fps)))
    for x, y in zip(a, b):
        old, new = label[at[int(x)]], label[at[int(y)]]
        label = [new if z == old else z for z in label]
    plain = components_plain(fps)
    assert len(set(zip(label, plain))) == len(set(plain)) == len(set(label))
    assert len(a) == len(fps) - len(set(plain))


def test_long_chains_become_one_component(spark):
    chain = spark.range(60).selectExpr("id AS a", "id + 1 AS b")
    assert {r.root for r in simhash_gray.components(chain).collect()} == {0}


def test_simhash_cases(odd, empty):
    rows = simhash_gray.near_duplicates(odd).collect()
    assert len(rows) == len(ODD)
    assert {r.component_id for r in rows if r.doc_id in (1, 2, 3)} == {1} and {r.component_id for r in rows if r.doc_id in (4, 5)} == {4}
    assert simhash_gray.near_duplicates(empty).count() == 0


# --- decontamination ---

def test_leaks_and_edits(spark):
    random.seed(9)
    words = ["".join(random.choice("abcdefgh") for _ in range(5)) for _ in range(3000)]
    item = lambda: [random.choice(words) for _ in range(30)]
    items = [(i, " ".join(item())) for i in range(20)] + [(98, "tiny one"), (99, None)]
    filler = lambda: " ".join(random.choice(words) for _ in range(80))
    edited = items[3][1].split()
    edited[10:11] = []
    edited[20:20] = ["new", "words"]
    edited[5] = "changed"
    docs = [(i, filler()) for i in range(40)] + [(100, f"{filler()} {items[0][1].upper()}, {filler()}"), (101, f"{filler()} {' '.join(edited)} {filler()}"), (102, " ".join(items[5][1].split()[:9]) + " " + filler()), (103, "a tiny one here")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): r for r in decontaminate.leaks(documents(spark, docs), bench).collect()}
    assert set(got) == {(100, 0), (101, 3), (103, 98)}
    assert got[100, 0].ratio == 1 and 0.7 < got[101, 3].ratio < 1
    assert (got[100, 0].begin_word, got[100, 0].end_word) == (80, 110)
    kept = {r.doc_id for r in decontaminate.without_leaks(documents(spark, docs), bench).collect()}
    assert kept == {k for k, _ in docs} - {100, 101, 103}
    small = decontaminate.leaks(documents(spark, docs), bench, decontaminate.AlignSettings(block_words=60))
    assert {(r.doc_id, r.item_id) for r in small.collect()} == set(got)


def test_alignment_as_plain():
    random.seed(1)
    for _ in range(100):
        a, b = [np.array([random.randint(0, 3) for _ in range(random.randint(1, 12))]) for _ in range(2)]
        h = np.zeros((len(a) + 1, len(b) + 1), int)
        for i in range(len(a)):
            for j in range(len(b)):
                h[i + 1, j + 1] = max(0, h[i, j] + (1 if a[i] == b[j] else -1), h[i, j + 1] - 1, h[i + 1, j] - 1)
        assert decontaminate.align(a, b)[0] == h.max()


def test_decontamination_cases(spark, odd, empty):
    bench = spark.createDataFrame([(1, "same text here and there"), (1, "same text here and there"), (2, ""), (None, "a text without a key")], "item_id long, text string")
    rows = decontaminate.leaks(odd, bench).collect()
    assert collections.Counter(r.doc_id for r in rows) == {4: 2, 5: 4, None: 1}
    assert decontaminate.leaks(empty, bench).count() == 0 and decontaminate.leaks(odd, bench.limit(0)).count() == 0
    assert decontaminate.without_leaks(odd, bench.limit(0)).count() == len(ODD)


# --- mixing ---

def test_mixture_deviates_by_less_than_a_block(spark):
    sizes = {"a": 400, "b": 150, "c": 90, "d": 7}
    rows = [(i, s) for s, n in sizes.items() for i in range(n)]
    weights = {"a": 5, "b": 3, "c": 2, "d": 1}
    got = pfair_mix.mix(spark.createDataFrame(rows, "doc_id long, source string"), weights, block_rows=1).orderBy("place").collect()
    assert len(got) == len(rows) and [r.slot for r in got] == list(range(len(rows)))
    done, total = collections.Counter(), sum(weights.values())
    for t, r in enumerate(got[: 7 * total]):  # until the smallest source runs out
        done[r.source] += 1
        for s, w in weights.items():
            assert abs(done[s] - (t + 1) * w / total) < 1


def test_mixture_cases(spark, odd, empty):
    rows = pfair_mix.mix(odd).collect()
    assert len(rows) == len(ODD) and len({r.place for r in rows}) == len(ODD)
    assert pfair_mix.mix(empty).count() == 0
    none = spark.createDataFrame([(1, None), (2, "")], "doc_id long, source string")
    assert {r.source for r in pfair_mix.mix(none).collect()} == {""}
    with pytest.raises(ValueError):
        pfair_mix.mix(odd, {"s1": 0})


# --- pages ---

def test_main_text():
    label = "<html><head><title>t</title></head><body><nav><a>Home</a></nav><article><h1>Head</h1><p>Some words of text in an article.</p></article><footer>&copy; me</footer></body></html>"
    w = html_main_text.learn([label] * 20, html_main_text.HtmlSettings())
    page = "<nav><ul><li>Home<li>News</ul></nav><div class='ad'>Buy this now</div><div><h1>A &lt;title&gt;</h1><script>x='</p>'</script><p>First  para\ngraph <b>bo</b>ld &amp; more<br>line.<p>Second one with a few words<!-- no --><form>Sign <input></form><p>Third.</div><div class=\"comments\"><p>reader says so</p></div><footer>end</footer>"
    assert html_main_text.main_text(page, w) == "A <title> First para graph bold & more line. Second one with a few words Third."
    assert html_main_text.main_text("", w) == "" and html_main_text.main_text("<p>unclosed <b", w) == "unclosed"


def test_page_cases(spark):
    pages = spark.createDataFrame([(1, "u", None), (2, None, "<p>hello there</p>"), (2, None, "<p>hello there</p>")], "page_id long, url string, html string")
    rows = html_main_text.extract(pages).collect()
    assert sorted((r.page_id, r.text, r.n_chars) for r in rows) == [(1, "", 0), (2, "hello there", 11), (2, "hello there", 11)]
    assert html_main_text.extract(pages.limit(0)).count() == 0
