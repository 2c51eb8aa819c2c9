import hashlib
import random

import pytest

from tests.llm import brute
from trilist.llm import lines, mixing, repeats, simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, __ll_k1 string, gone string"


def table(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, 0, "x", "y") for i, t, s in rows], SCHEMA)


def texts(seed=1, n=60):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdefé") for _ in range(r.randint(1, 7)))
    passage = " ".join(word() for _ in range(150))
    out = []
    for _ in range(n):
        t = " ".join(word() for _ in range(r.randint(0, 200)))
        if r.random() < 0.4:
            cut = r.randint(0, len(passage) - 500)
            t += passage[cut : cut + r.randint(380, 600)] + t[: r.randint(0, 50)]
        out.append(t)
    return [*out, out[3], out[5], None, "", "a" * 1500, "ab" * 700, passage, passage]


def digested(row):
    return (row.doc_id, row.n_bytes, row.n_removed, row.n_spans, hashlib.sha256(row.kept).hexdigest(), row.n_passage_words)


@pytest.mark.parametrize("block", [repeats.BLOCK, 700])
def test_repeats_equal_brute_force(spark, block):
    rows = [(i, t) for i, t in enumerate(texts())]
    got = repeats.without_repeats(table(spark, [(i, t, "s") for i, t in rows]), 400, block=block)
    assert sorted(map(digested, got.collect())) == sorted((*r, n) for r, n in zip(brute.repeats(rows), brute.passages(rows)))


def test_repeats_short_depth_and_nulls(spark):
    rows = [(1, "xyz" * 30), (1, "xyz" * 30), (None, "q" * 70), (None, None), (2, "")]
    got = repeats.without_repeats(table(spark, [(i, t, None) for i, t in rows]), 60, 8).collect()
    assert sorted((str(x.doc_id), x.n_removed) for x in got) == sorted((str(i), r[2]) for (i, _), r in zip(rows, brute.repeats(rows, 60)))
    assert repeats.without_repeats(table(spark, [])).count() == 0


def test_repeats_of_equal_rows_and_very_long_texts(spark):
    r = random.Random(9)
    passage = " ".join(str(r.random()) for _ in range(60))
    long = " ".join(str(r.random()) for _ in range(170_000))
    rows = [(7, "start " + passage + " end")] * 40 + [(8, "other " + passage), (9, long), (10, long[2_500_000:2_500_900]), (11, "x y " * 20)]
    got = {x.doc_id: x for x in repeats.without_repeats(table(spark, [(i, t, "s") for i, t in rows])).collect()}
    assert len(long) > repeats.BLOCK and got[9].n_removed == got[10].n_removed == 900 and got[9].n_passage_words == 0 == got[11].n_passage_words
    assert got[7].n_removed == len(rows[0][1]) and got[8].n_removed == len(passage) + 1 and got[7].n_passage_words == got[8].n_passage_words == 60


def test_simhash_equals_brute_force(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    got = simhash.op4_simhash_grid(spark, sf).collect()
    assert sorted(map(tuple, got)) == sorted(brute.simhash(docs))


def test_links_of_crowded_cells_are_exact(spark):
    r = random.Random(5)
    base = [r.getrandbits(64) for _ in range(3)]
    fps = {b ^ sum(1 << r.randrange(64) for _ in range(r.randint(0, 3))) % 2**64 for b in base for _ in range(60)}
    signed = [x - 2**64 if x >= 2**63 else x for x in fps]
    from trilist.llm.common import components

    def groups(limit):
        edges = simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"), limit)
        return {(x.node, x.root) for x in components(edges).collect()}

    root = {x: x for x in signed}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in signed:
        for b in signed:
            if a < b and ((a ^ b) & (2**64 - 1)).bit_count() <= 2:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    want = {(x, find(x)) for x in signed if find(x) != x}
    assert groups(64) == groups(2) == want


def test_lines_edge_cases(spark):
    rows = [(i, f"own line number {i} is here\nshared footer line, long enough\n\nend", f"s{i}") for i in range(12)]
    rows += [(None, None, None), (50, "", "s1"), (51, "shared footer line, long enough", None), (51, "shared footer line, long enough", None)]
    got = {(r.doc.doc_id, r.text, r.n_gone) for r in lines.dedup_lines(table(spark, rows)).collect()}
    assert (0, rows[0][1], 0) in got
    assert (5, "own line number 5 is here\n\nend", 1) in got
    assert (51, "", 1) in got and (50, "", 0) in got and (None, None, 0) in got
    assert lines.dedup_lines(table(spark, [])).count() == 0


def test_near_threshold_lines_are_counted_exactly(spark):
    rows = [(i, f"a line that is on {n} sites", f"s{i % n}") for n in (8, 9, 10, 11, 12) for i in range(n * 3)]
    got = lines.dedup_lines(table(spark, [(k, t, s) for k, (_, t, s) in enumerate(rows)]), lg_k=4).filter("text = ''")
    assert got.count() == 29 + 32 + 35


def test_mix_meets_targets(spark):
    rows = [(i, "w " * (i % 7), ["a", "b", None][i % 3]) for i in range(300)] + [(7, "w w w", "a")] * 3 + [(None, None, "z")]
    plan = mixing.plan_mix(table(spark, rows), rows_per_range=16).collect()
    assert len(plan) == len(rows)
    for name in {p.name for p in plan}:
        mine = [p for p in plan if p.name == name]
        assert sum(p.taken for p in mine) == int(mine[0].target)
        assert all(0 <= p.taken <= 2 * p.size for p in mine)
    total = sum(p.size for p in plan)
    assert abs(sum({p.name: p.target for p in plan}.values()) - 1.5 * total) < 0.01
    assert mixing.plan_mix(table(spark, [])).count() == 0
    spread = mixing.prefixed(spark.range(50).selectExpr("'s' AS name", "id AS range", "id % 7 AS range_size"), 4).orderBy("range").collect()
    assert [x.offset for x in spread] == [sum(i % 7 for i in range(k)) for k in range(50)]
    clash = mixing.mix_documents(table(spark, rows).selectExpr("*", "'x' AS mix_size", "1 AS mix_copies"))
    assert len(set(clash.columns)) == len(clash.columns) and clash.filter("mix_size > 0").count() > 0
    mix = mixing.mix_documents(table(spark, rows))
    assert mix.columns[:7] == table(spark, []).columns and mix.filter("mix_taken = 0").count() == 0


@pytest.mark.parametrize(("unit", "depth", "gram"), [(repeats.BYTES, 60, 8), (repeats.WORDS, 12, 4)])
def test_short_texts_are_hashed_together(spark, monkeypatch, unit, depth, gram):
    """A batch of many texts is one array, so that each text does not cost its own round of calls; null, empty and short texts leave the others' windows as they are."""
    import pyarrow as pa

    class Docs:
        def select(self, *_):
            return self

        def mapInArrow(self, run, _):
            return run

    built, real = [], repeats.Rolling.__init__
    monkeypatch.setattr(repeats.Rolling, "__init__", lambda self, data: built.append(len(data)) or real(self, data))
    texts = [None, b"", b"few words", b"  "] + [" ".join(f"w{(i * 7 + k * k) % 97}é" for k in range(30 + i % 5)).encode() + b"\t" * (i % 3) for i in range(400)] + [None]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts)), pa.int64()), pa.array(range(len(texts)), pa.int64()), pa.array(texts, pa.binary())], names=["a", "b", "text"])
    run = repeats.anchor_rows(Docs(), depth, gram, unit)
    rows = lambda batches: sorted(tuple(r.values()) for b in run(iter(batches)) for r in b.to_pylist())
    together = rows([batch.slice(1, 300), batch.slice(301)])
    assert len(built) <= 8 and len({r[0] for r in together}) == 400
    assert together == rows([batch.slice(i, 1) for i in range(1, len(texts))])
