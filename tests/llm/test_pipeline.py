import random

import corpus_pipeline as C
from hubloom.llm.common import saved, table


def test_stages_in_order(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select(C.COLUMNS)
    kinds = docs.dtypes
    ids = {r["doc_id"] for r in docs.select("doc_id").collect()}
    for name, stage in C.STAGES:
        docs = saved(stage(spark, docs, sf_dir), "test")
        now = [r["doc_id"] for r in docs.select("doc_id").collect()]
        assert len(now) == len(set(now)) and set(now) <= ids and len(now) > 0.5 * len(ids)
        ids = set(now)
        if name != C.STAGES[-1][0]:
            assert docs.dtypes == kinds
    assert docs.where("n_tokens > 0").count() > 0


def test_copies_and_nulls(spark, sf_dir):
    text = " ".join(f"word{i} and" for i in range(200))
    rows = [(1, text, "en", "a", 1), (2, text, "en", "b", 1), (3, text.replace("word7 ", "other "), None, None, None), (4, None, None, None, None), (None, "x", None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(str(r["doc_id"]) for r in C.near_dedup(spark, docs, sf_dir).collect()) == ["1", "4", "None"]
    assert C.decontaminate(spark, docs, sf_dir).count() == 5
    assert C.line_dedup(spark, docs, sf_dir).count() == 5
    assert C.near_dedup(spark, docs.limit(0), sf_dir).count() == 0


def test_near_dedup_against_brute_force(spark, sf_dir):
    rnd = random.Random(21)
    word = lambda: "".join(rnd.choice("abcdefghij") for _ in range(6))
    rows, i = [], 0
    for k in range(60):  # pairs a little above and below the limit
        words = [word() for _ in range(300)]
        other = list(words)
        for at in range(5, 300, 300 // (6 if k % 2 else 9)):
            other[at] = word()
        rows += [(i, " ".join(words)), (i + 1, " ".join(other))]
        i += 2
    base = [word() for _ in range(100)]
    for _ in range(90):  # a large group about one text
        copy = list(base)
        copy[rnd.randrange(100)] = word()
        rows.append((i, " ".join(copy)))
        i += 1
    sets = {d: {tuple(w[j : j + 5]) for j in range(len(w) - 4)} for d, w in ((d, t.split()) for d, t in rows)}
    root = {d: d for d in sets}

    def top(d):
        while root[d] != d:
            d = root[d]
        return d

    for a in sets:
        for b in sets:
            if a < b and 10 * len(sets[a] & sets[b]) >= 8 * len(sets[a] | sets[b]):
                root[max(top(a), top(b))] = min(top(a), top(b))
    docs = spark.createDataFrame([(d, t, "en", "x", 1) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r["doc_id"] for r in C.near_dedup(spark, docs, sf_dir).collect()) == sorted(d for d in root if top(d) == d)


SHAPE = "doc_id long, text string, lang string, source string, n_chars long"


def test_equal_and_null_ids(spark, sf_dir):
    leak = table(spark, sf_dir, "benchmark").first()["text"]
    clean = "some clean words that stand in no benchmark item of any kind"
    rows = [(1, clean, "en", "a", 1), (1, f"before {leak} after", "en", "a", 1), (None, leak, None, None, None), (None, clean + " at all", None, None, None), (2, clean, "en", "a", 1), (2, clean, "en", "a", 1)]
    docs = spark.createDataFrame(rows, SHAPE)
    left = [(r["doc_id"], r["text"]) for r in C.decontaminate(spark, docs, sf_dir).collect()]
    assert sorted(left, key=str) == sorted([(1, clean), (None, clean + " at all"), (2, clean), (2, clean)], key=str)
    left = [(r["doc_id"], r["text"]) for r in C.near_dedup(spark, docs, sf_dir).collect()]
    assert sorted(left, key=str) == sorted([(1, clean), (1, f"before {leak} after")], key=str)  # those without id are near copies


def test_empty_tables(spark, sf_dir):
    for name, stage in C.STAGES:
        assert stage(spark, spark.createDataFrame([], SHAPE), sf_dir).count() == 0, name
