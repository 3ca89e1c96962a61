"""The near-duplicate stage against Jaccard similarities of all pairs."""

import itertools
import random

import corpus_pipeline
from levelindex.llm.common import LOWER_TABLE


def plain_set(text):
    w = (text or "").encode().translate(LOWER_TABLE).split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def plain_kept(rows):
    """Smallest keys of the components of all pairs with a similarity of 0.8 or more."""
    sets, root = [plain_set(t) for _, t in rows], list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, j in itertools.combinations(range(len(rows)), 2):
        both, either = len(sets[i] & sets[j]), len(sets[i] | sets[j])
        if 5 * both >= 4 * either:
            root[find(i)] = find(j)
    least = {}
    for i, (k, _) in enumerate(rows):
        least[find(i)] = min(k, least.get(find(i), k))
    return sorted(least.values())


def edited(rng, words, n, vocabulary):
    out = list(words)
    for _ in range(n):
        out[rng.randrange(len(out))] = rng.choice(vocabulary)
    return out


def test_stage_as_all_pairs(spark, sf):
    rng = random.Random(5)
    vocabulary = [f"w{i}" for i in range(400)]
    texts = [None, "", " \n", "a b", "A  b", "a b c d e", "a b c d e f"]
    line = rng.choices(vocabulary, k=12)
    for size in (9, 40, 100, 300):
        for _ in range(6):
            base = rng.choices(vocabulary, k=size)
            texts += [" ".join(base)] + [" ".join(edited(rng, base, n, vocabulary)) for n in range(size // 50 + 2) for _ in range(2)]
            texts.append(" ".join(base[: size // 2] + line + base[size // 2 :]))
    chain = rng.choices(vocabulary, k=200)
    for _ in range(30):  # each like the one before, the ends unlike
        chain = edited(rng, chain, 2, vocabulary)
        texts.append(" ".join(chain))
    rows = list(enumerate(texts))
    rng.shuffle(rows)
    docs = spark.createDataFrame([(k, t, "en", "s", len(t or "")) for k, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in corpus_pipeline.drop_near_duplicates(spark, docs, sf).collect()) == plain_kept(rows)


def test_stage_on_a_given_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    assert sorted(r.doc_id for r in corpus_pipeline.drop_near_duplicates(spark, docs, sf).collect()) == plain_kept(rows)
