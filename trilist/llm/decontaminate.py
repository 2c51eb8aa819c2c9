"""Benchmark decontamination by training suffix arrays.

Each batch of documents is a shard. Its words become numbers of the benchmark's vocabulary (0 for any other word), and the
suffixes that can match at all (as many known words in a row as the test window has, the first of them a window's first
word) are sorted into a suffix array. Every test suffix, cut to its window of ``width`` words or to its whole item when
that is shorter, is then looked up by two binary searches; the interval between them holds all its verbatim occurrences.
Adjacent occurrences on one diagonal join to the longest matches.

The benchmark goes to the executors in blocks of about ``block_words`` words, so no broadcast grows with it beyond that. One
block needs one pass in which documents never move; with more, each block is broadcast, passed over all documents, and
destroyed before the next, and what the passes hit is joined to the documents by row.

Edge cases: null text has no words and is clean; an item without words has no window; a null item_id is the id "null"; equal
rows get equal results; an empty benchmark or document table is fine; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.llm.common import K1, K2, bounded_batches, discard, join_hot, materialise, packed, read_table

WIDTH, BLOCK_WORDS = 10, 4_000_000


def letters() -> bytes:
    """Byte table: digits, letters and bytes from 128 on are word bytes, A-Z in lower case, all else a space."""
    keep = {*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)}
    return bytes(c + 32 if 0x41 <= c <= 0x5A else c if c in keep else 0x20 for c in range(256))


def words_of(raw: bytes, table: bytes) -> list[bytes]:
    return raw.translate(table).split()


def packed_keys(ids, at, length: int):
    """The length word numbers from each position on, as big-endian byte strings that sort like the numbers."""
    import numpy as np

    return np.ascontiguousarray(ids[at[:, None] + np.arange(length)].astype(">u4")).view(f"S{4 * length}").ravel()


class TestIndex:
    """Windows of one block of benchmark items, by length, sorted and each listed with its places (item, offset)."""

    __test__ = False

    def __init__(self, items: list[tuple[str, bytes]], width: int):
        import numpy as np

        table = letters()
        self.names, self.vocabulary, by_length = [], {}, {}
        for name, raw in items:
            words = words_of(raw, table)
            if not words:
                continue
            ids = np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words], np.uint32)
            n = min(width, len(ids))
            starts = np.arange(len(ids) - n + 1)
            by_length.setdefault(n, []).append((packed_keys(ids, starts, n), np.full(len(starts), len(self.names)), starts))
            self.names.append(name)
        self.windows = {}
        for n, parts in by_length.items():
            keys, item, offset = map(np.concatenate, zip(*parts))
            order = np.argsort(keys, kind="stable")
            unique, first = np.unique(keys[order], return_index=True)
            starters = np.zeros(len(self.vocabulary) + 1, bool)
            starters[unique.view(">u4").reshape(len(unique), n)[:, 0]] = True
            self.windows[n] = (unique, np.r_[first, len(keys)], item[order], offset[order], starters)

    def search(self, ids, n: int):
        """Occurrences of the windows of n words in a shard: positions, and the number of the window for each."""
        import numpy as np

        unique, _, _, _, starters = self.windows[n]
        starters = np.r_[starters, np.zeros(len(self.vocabulary) + 1 - len(starters), bool)]
        stops = np.flatnonzero(ids == 0)
        run = stops[np.searchsorted(stops, np.arange(len(ids)))] - np.arange(len(ids))
        at = np.flatnonzero((run >= n) & starters[ids])
        if not len(at):
            return at, at
        keys = packed_keys(ids, at, n)
        order = np.argsort(keys, kind="stable")
        suffixes = keys[order]
        low, high = np.searchsorted(suffixes, unique, "left"), np.searchsorted(suffixes, unique, "right")
        count = high - low
        window = np.repeat(np.arange(len(unique)), count)
        place = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + np.repeat(low, count)
        return at[order[place]], window


def blocks(benchmark: DataFrame, width: int, block_words: int) -> Iterator[TestIndex]:
    """Indexes of the items, in blocks; the driver holds the texts and the index of one block at a time."""
    items, size = [], 0
    rows = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("name"), F.col("text").cast("binary").alias("raw")).filter("raw IS NOT NULL")
    for row in rows.toLocalIterator():
        items.append((row.name, bytes(row.raw)))
        size += len(row.raw) // 2
        if size >= block_words:
            yield TestIndex(items, width)
            items, size = [], 0
    if items:
        yield TestIndex(items, width)


def shard_ids(texts: list[bytes], vocabulary: dict, table: bytes, gap: int):
    """Word numbers of all texts in one array, gap zeros after each; and where each text begins, and its word count."""
    from itertools import repeat

    import numpy as np

    parts, starts, counts, at = [], [], [], 0
    for raw in texts:
        words = words_of(raw, table)
        ids = np.zeros(len(words) + gap, np.uint32)
        ids[: len(words)] = np.fromiter(map(vocabulary.get, words, repeat(0)), np.uint32, len(words))
        parts.append(ids)
        starts.append(at)
        counts.append(len(words))
        at += len(ids)
    return np.concatenate(parts), np.array(starts), counts


def matched(texts: list[bytes], index: TestIndex, width: int) -> list[tuple]:
    """For each text: its word count, its hit stretches [s, e), its item names, its maximal matches (item, doc word, item word, words)."""
    import numpy as np

    ids, starts, counts = shard_ids(texts, index.vocabulary, letters(), width)
    lines: list[dict] = [{} for _ in texts]
    for n, (_, first, item, offset, _) in index.windows.items():
        at, window = index.search(ids, n)
        text = np.searchsorted(starts, at, "right") - 1
        for t, p, w in zip(text.tolist(), (at - starts[text]).tolist(), window.tolist()):
            for k in range(first[w], first[w + 1]):
                lines[t].setdefault((int(item[k]), p - int(offset[k]), n), []).append(p)
    out = []
    for count, found in zip(counts, lines):
        matches = []
        for (item, shift, n), places in found.items():
            places.sort()
            begin = places[0]
            for x, y in zip(places, [*places[1:], None]):
                if y is None or y > x + 1:
                    matches.append((index.names[item], begin, begin - shift, x - begin + n))
                    begin = y
        spans: list[list[int]] = []
        for s, e in sorted((m[1], m[1] + m[3]) for m in matches):
            if spans and s <= spans[-1][1]:
                spans[-1][1] = max(spans[-1][1], e)
            else:
                spans.append([s, e])
        out.append((count, spans, sorted({m[0] for m in matches}), sorted(matches)))
    return out


MATCHES = "array<struct<item_id: string, doc_word: bigint, item_word: bigint, words: bigint>>"
ARROW_MATCHES = pa.list_(pa.struct([("item_id", pa.string()), ("doc_word", pa.int64()), ("item_word", pa.int64()), ("words", pa.int64())]))


def as_structs(matches: list[tuple]) -> list[dict]:
    return [dict(zip(("item_id", "doc_word", "item_word", "words"), m)) for m in matches]


def texts_in(column) -> list[bytes]:
    return [(x or "").encode("utf-8", "surrogatepass") for x in column.field("text").to_pylist()]


def contamination(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, block_words: int = BLOCK_WORDS) -> DataFrame:
    """Rows (doc, n_words, n_hit, items, matches): the row of docs as a struct, its sorted item names and its maximal verbatim matches."""
    spark = docs.sparkSession
    bounded_batches(spark)
    rows = packed(docs).select("doc", K1, K2)
    kind = rows.schema["doc"].dataType.simpleString()
    indexes = blocks(benchmark, width, block_words)
    head, more = next(indexes, TestIndex([], width)), next(indexes, None)
    shape = f"doc {kind}, n_words long, n_hit long, items array<string>, matches {MATCHES}"

    def finished(doc, found) -> pa.RecordBatch:
        counts, spans, items, matches = zip(*found)
        hits = pa.array([sum(e - s for s, e in x) for x in spans], pa.int64())
        return pa.RecordBatch.from_arrays([doc, pa.array(counts, pa.int64()), hits, pa.array(items, pa.list_(pa.string())), pa.array(map(as_structs, matches), ARROW_MATCHES)], names=["doc", "n_words", "n_hit", "items", "matches"])

    if more is None:
        held = spark.sparkContext.broadcast(head)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    yield finished(b.column(0), matched(texts_in(b.column(0)), held.value, width))

        return rows.select("doc").mapInArrow(run, shape)

    # one block after the other: each is in the executors' memory alone, and leaves only what it hit
    parts, block = [], head
    while block is not None:
        held = spark.sparkContext.broadcast(block)

        def scan(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    found = matched(texts_in(b.column(0)), held.value, width)
                    hit = [i for i, x in enumerate(found) if x[3]]
                    at = pa.array(hit, pa.int64())
                    yield pa.RecordBatch.from_arrays([b.column(1).take(at), b.column(2).take(at), pa.array([as_structs(found[i][3]) for i in hit], ARROW_MATCHES)], names=[K1, K2, "matches"])

        parts.append(materialise(rows.mapInArrow(scan, f"{K1} long, {K2} long, matches {MATCHES}"), "decontaminate-block"))
        held.destroy()
        block, more = more, next(indexes, None)
    every = parts[0]
    for part in parts[1:]:
        every = every.unionByName(part)
    # equal rows have one key and equal matches: a set holds them once
    by_row = materialise(every.groupBy(K1, K2).agg(F.flatten(F.collect_set("matches")).alias("matches"), F.count("*").alias("n")), "decontaminate-matches")
    discard(*parts)

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = letters()
        for b in batches:
            if not b.num_rows:
                continue
            out = []
            for raw, given in zip(texts_in(b.column(0)), b.column(1).to_pylist()):
                matches = sorted((m["item_id"], m["doc_word"], m["item_word"], m["words"]) for m in given or ())
                spans, end = [], 0
                for s, e in sorted((m[1], m[1] + m[3]) for m in matches):
                    if e > end:
                        spans.append((max(s, end), e))
                        end = e
                out.append((len(words_of(raw, table)), spans, sorted({m[0] for m in matches}), matches))
            yield finished(b.column(0), out)

    joined = join_hot(rows, by_row, [K1, K2], "n", max(1, rows.count()), how="left")
    return joined.select("doc", "matches").mapInArrow(join, shape)


def longest_matches(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, block_words: int = BLOCK_WORDS) -> DataFrame:
    """Maximal verbatim matches: rows (doc_id, item_id, doc_word, item_word, words), places counted in words from 0."""
    found = contamination(docs.select("doc_id", "text"), benchmark, width, block_words)
    return found.select("doc.doc_id", F.explode("matches").alias("m")).select("doc_id", "m.*")


def op9_suffix_decontamination(spark, sf_dir: str) -> DataFrame:
    """Ten-word windows of all benchmark items in all documents; and each document's longest match (ties: first in it, item, place in the item)."""
    found = contamination(read_table(spark, sf_dir, "documents").select("doc_id", "text"), read_table(spark, sf_dir, "benchmark"))
    order = F.transform("matches", lambda m: F.struct((-m["words"]).alias("less"), m["doc_word"].alias("doc_word"), m["item_id"].alias("item_id"), m["item_word"].alias("item_word")))
    best = F.array_min(order)
    return found.select(
        "doc.doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"),
        F.size("matches").cast("long").alias("n_matches"), F.coalesce(-best["less"], F.lit(0)).cast("long").alias("longest_words"), best["item_id"].alias("longest_item"), best["doc_word"].alias("longest_doc_word"), best["item_word"].alias("longest_item_word"),
    )


OP9_SQL = r"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
i AS (
  SELECT row_number() OVER () AS ir, coalesce(item_id::VARCHAR, 'null') AS item,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
iw AS (
  SELECT ir, item, q, least(10, len(w)) AS n, array_to_string(list_slice(w, q, q + least(10, len(w)) - 1), ' ') AS k
  FROM (SELECT ir, item, w, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS q FROM i WHERE len(w) > 0)),
dw AS (
  SELECT r, p, n, array_to_string(list_slice(w, p, p + n - 1), ' ') AS k
  FROM (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, (SELECT DISTINCT n FROM iw))),
hit AS (SELECT r, p, n, ir, item, q FROM dw JOIN iw USING (n, k)),
cover AS (SELECT r, count(DISTINCT q) AS n_hit FROM (SELECT DISTINCT r, p, n FROM hit), unnest(range(p, p + n)) AS t(q) GROUP BY r),
its AS (SELECT r, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT r, item FROM hit) GROUP BY r),
runs AS (SELECT *, p - row_number() OVER (PARTITION BY r, ir, p - q ORDER BY p) AS island FROM hit),
matches AS (SELECT r, ir, item, min(p) - 1 AS doc_word, min(q) - 1 AS item_word, max(p) - min(p) + any_value(n) AS words FROM runs GROUP BY r, ir, item, p - q, island),
best AS (SELECT r, doc_word, item, item_word, words, count(*) OVER (PARTITION BY r) AS n_matches, row_number() OVER (PARTITION BY r ORDER BY words DESC, doc_word, item, item_word) AS place FROM matches)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated, coalesce(n_matches, 0)::BIGINT AS n_matches,
       coalesce(words, 0)::BIGINT AS longest_words, b.item AS longest_item, b.doc_word::BIGINT AS longest_doc_word, b.item_word::BIGINT AS longest_item_word
FROM d LEFT JOIN cover USING (r) LEFT JOIN its USING (r) LEFT JOIN (SELECT * FROM best WHERE place = 1) b USING (r)
"""
