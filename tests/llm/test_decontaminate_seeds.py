"""Documents whose seeds are absent elsewhere, or very common, still meet their item."""

from levelindex.llm import decontaminate


def found(spark, items, docs):
    bench, table = spark.createDataFrame(items, "item_id long, text string"), spark.createDataFrame(docs, "doc_id long, text string")
    got = {(r.doc_id, r.item_id): r.ratio for r in decontaminate.leaks(table, bench).collect()}
    assert {r.doc_id for r in decontaminate.without_leaks(table, bench).collect()} == {k for k, _ in docs} - {k for k, _ in got}
    return got


def test_items_most_of_whose_seeds_occur_nowhere(spark):
    words = [f"a{i}" for i in range(36)]
    edited = [f"x{i}" if i % 6 == 5 else w for i, w in enumerate(words)]
    half = [f"b{i}" for i in range(31)]
    docs = [(1, " ".join(edited)), (2, "before " + " ".join(half[:16]) + " after"), (3, "none of it")]
    got = found(spark, [(10, " ".join(words)), (11, " ".join(half))], docs)
    assert set(got) == {(1, 10), (2, 11)} and got[1, 10] > 0.6 and got[2, 11] > 0.5


def test_documents_with_the_common_part_only(spark):
    words = [f"c{i}" for i in range(40)]
    docs = [(i, f"u{i} " + " ".join(words[:21]) + f" v{i}") for i in range(60)] + [(i, f"u{i} " + " ".join(words[:8]) + f" v{i}") for i in range(60, 90)] + [(99, " ".join(words))]
    got = found(spark, [(10, " ".join(words))], docs)
    assert {d for d, _ in got} == {*range(60), 99} and got[99, 10] == 1
