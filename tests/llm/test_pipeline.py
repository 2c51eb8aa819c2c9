import random

import pytest

import corpus_pipeline
from trilist.llm import similar

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, stays string"


def texts():
    r = random.Random(3)
    word = lambda: "".join(r.choice("abcdefghij") for _ in range(r.randint(2, 8)))
    base = [[word() for _ in range(r.randint(60, 300))] for _ in range(30)]
    rows = [(i, " ".join(b)) for i, b in enumerate(base)]
    for k in range(60):
        b = list(base[k % 6])
        for _ in range(r.randint(0, 3)):
            b[r.randrange(len(b))] = word()
        rows.append((100 + k, " ".join(b)))
    return [*rows, (200, ""), (201, None), (202, "one two"), (203, "one two"), (3, rows[3][1]), (None, rows[4][1])]


def test_near_duplicates_equal_brute_force(spark):
    rows = texts()
    docs = spark.createDataFrame([(i, t, "en", "s", 0, "x") for i, t in rows], SCHEMA)
    got = sorted((x.doc.doc_id for x in similar.near_duplicates(docs).filter("stays").collect()), key=str)
    sets = [set(similar.shingle_hashes(t, 5).tolist()) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    groups = {}
    for i, (d, _) in enumerate(rows):
        groups.setdefault(find(i), []).append((d is None, d))
    assert got == sorted((min(g)[1] for g in groups.values()), key=str)


def crowd():
    """Families that share a passage: 40 copies like a base, one cut by its end, and one cut at both ends that only the last is like."""
    r = random.Random(11)
    words = lambda n: ["".join(r.choice("abcdefghijklmnop") for _ in range(7)) for _ in range(n)]
    passage, rows = words(130), []
    for _ in range(8):
        base = words(60) + passage + words(64)
        rows += [base + words(2) for _ in range(40)] + [base[:-2], base[49:-2]]
    r.shuffle(rows)
    return list(enumerate(map(" ".join, rows)))


@pytest.mark.parametrize("block", [similar.BLOCK, 3])
def test_crowded_bands_lose_no_pair(spark, monkeypatch, block):
    monkeypatch.setattr(similar, "BLOCK", block)
    rows = crowd()
    docs = spark.createDataFrame([(i, t, "en", "s", 0, "x") for i, t in rows], SCHEMA)
    got = {x.doc.doc_id for x in similar.near_duplicates(docs).filter("stays").collect()}
    sets = [set(similar.shingle_hashes(t, 5).tolist()) for _, t in rows]
    root = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            if root[i] != root[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                root = [min(root[i], root[j]) if x in (root[i], root[j]) else x for x in root]
    assert len(set(root)) == 8 and got == set(root)


def test_stages_keep_columns_and_clean_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = docs
    for name, stage in corpus_pipeline.STAGES:
        done = stage(spark, rows, sf)
        assert done.columns[: len(docs.columns)] == docs.columns and done.count() <= rows.count()
        rows = done
    assert corpus_pipeline.run(spark, sf).count() == rows.count() > 0


def test_empty_table(spark, sf):
    rows = spark.read.parquet(f"{sf}/documents.parquet").filter("doc_id < 0")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, rows, sf).count() == 0


def test_nothing_learned_rejects_no_letters_only(spark, sf):
    rows = spark.createDataFrame([(1, "plain words", None, "s", 0, "x"), (2, "12 3", None, "s", 0, "x"), (3, None, None, "s", 0, "x"), (4, "é", None, "s", 0, "x")], SCHEMA)
    assert {r.doc_id for r in corpus_pipeline.identify_language(spark, rows, sf).collect()} == {1, 4}


def test_short_boilerplate_lines_go(spark, sf):
    rows = [(i, f"a line of document number {i}\nMenu\n\n \nend {i}", "en", f"s{i}", 0, "x") for i in range(12)]
    got = corpus_pipeline.dedup_lines(spark, spark.createDataFrame(rows, SCHEMA), sf)
    assert {r.doc_id: r.text for r in got.collect()} == {r[0]: r[1] if r[0] == 0 else r[1].replace("Menu\n", "") for r in rows}
