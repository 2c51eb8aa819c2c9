"""Suffix-array dedup by a depth-limited radix sort of suffixes, most significant digit first.

Suffixes matter only through their first ``depth`` bytes (the window that starts there). A window's digits, from the most
significant on: (1) its anchor, the window's smallest hashed ``gram``-byte string, leftmost on ties, with the anchor's
place in the window; (2) the bytes that the windows of one stretch of 32 neighbouring places share; (3) the whole window. Each pass
deals suffixes by one more digit and drops those that are alone, so the equal groups after the last pass are exactly the
repeated windows. Neighbouring suffixes that have the same anchor travel as one row (a region) as long as they stay
together: a region that occurs twice as a whole is settled at once, and only stretches where a match begins or ends are
opened into single windows.

All digits are hashes of byte strings by content: 64 bits each, compared only among windows with the same anchor.
Removed bytes are those of any repeated window; overlaps count; windows are judged on the input.

The same passes run over words in place of bytes (``unit``): there a passage counts where another document has it too, so
``shared_passages`` finds passages of more than 50 words across documents, whatever their length in bytes.

Edge cases: null text is empty; texts shorter than ``depth`` have no window; equal rows repeat each other's bytes, but are
one document as to passages; texts of any length are worked in blocks of ``block`` symbols; an empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.llm.common import K1, K2, bounded_batches, discard, join_hot, materialise, read_table, release, with_row_key

DEPTH, GRAM, STRETCH = 400, 48, 32
PASSAGE, PASSAGE_GRAM = 51, 8
BLOCK = 1 << 21
CHUNK, PORTION = 1 << 17, 1 << 20


def joined_bytes(column):
    """The bytes of a column of binaries (null: none) as one array, and where each value begins in it, the end included."""
    import numpy as np

    column = column.fill_null(b"") if column.null_count else column
    bounds = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(column.buffers()[2] or b"", np.uint8)[bounds[0] : bounds[-1]]
    return data, bounds - bounds[0]


def portions(batches: Iterator[pa.RecordBatch], at: int | str) -> Iterator[pa.RecordBatch]:
    """The batches in runs of rows with about PORTION bytes in column at, single rows of more by themselves."""
    import numpy as np

    for b in batches:
        bounds, i = joined_bytes(b.column(at))[1], 0
        while i < b.num_rows:
            j = max(i + 1, int(np.searchsorted(bounds, bounds[i] + PORTION, "right")) - 1)
            yield b.slice(i, j - i)
            i = j


def spread(counts):
    """For rows that make counts[i] rows each: the row that each comes from, and its number within it."""
    import numpy as np

    row = np.repeat(np.arange(len(counts)), counts)
    return row, np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts)


def listed(column):
    """A column of lists of structs: the row of each struct, and the structs' fields by name."""
    import pyarrow.compute as pc

    inner = column.flatten()
    return pc.list_parent_indices(column).to_numpy(), {f.name: x.to_numpy() for f, x in zip(inner.type, inner.flatten())}


@dataclass(frozen=True)
class Unit:
    """What windows are made of, and when equal windows count as repeated: m is their number, x and y are the least and largest key of their rows."""

    name: str
    dtype: str
    width: int
    carried: tuple[str, ...]
    repeated: str

    def symbols(self, column):
        """All texts of a column of binaries as one array, its bytes or 64-bit hashes of its words (runs of bytes other than ASCII white space), and where each text begins in it."""
        import numpy as np

        data, bounds = joined_bytes(column)
        if self.name == "byte":
            return data, bounds
        word = np.ones(256, bool)
        word[[0x20, *range(0x09, 0x0E)]] = False
        inside = word[data]
        begins, ends = inside.copy(), inside.copy()
        begins[1:] &= ~inside[:-1]
        ends[:-1] &= ~inside[1:]
        # a text's first and last byte have no neighbours in other texts
        at = bounds[:-1][np.diff(bounds) > 0]
        begins[at] = inside[at]
        at = bounds[1:][np.diff(bounds) > 0] - 1
        ends[at] = inside[at]
        begins, ends = np.flatnonzero(begins), np.flatnonzero(ends) + 1
        return Rolling(data).of(begins, ends), np.searchsorted(begins, bounds)

    def first(self) -> list:
        given = {"m": F.count("*"), "x": F.min(K1), "y": F.max(K1)}
        return [given[c].alias(c) for c in self.carried]

    def merged(self) -> list:
        given = {"m": F.sum("m"), "x": F.min("x"), "y": F.max("y")}
        return [given[c].alias(c) for c in self.carried]


BYTES = Unit("byte", "u1", 1, ("m",), "m > 1")
WORDS = Unit("word", "u8", 8, ("m", "x", "y"), "x <> y")


class Rolling:
    """Polynomial hashes (mod 2^64) of all substrings of one string of bytes or word hashes, from running sums."""

    base = 0x9E3779B97F4A7C15
    inverse = pow(base, -1, 2**64)
    powers: list = []

    def __init__(self, data):
        import numpy as np

        n = len(data)
        if not Rolling.powers or len(Rolling.powers[0]) < n + 1:
            size = max(4096, 2 * n)
            Rolling.powers = [np.multiply.accumulate(np.r_[np.uint64(1), np.full(size, b, np.uint64)]) for b in (Rolling.base, Rolling.inverse)]
            Rolling.letters = np.random.default_rng(2).integers(0, 2**64, 256, dtype=np.uint64)
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum((Rolling.letters[data] if data.dtype == np.uint8 else data) * Rolling.powers[0][:n], out=self.sums[1:])

    def of(self, start, end):
        """Hashes of data[start:end] for arrays of bounds, well mixed."""
        import numpy as np

        return self.stirred((self.sums[end] - self.sums[start]) * Rolling.powers[1][start])

    def every(self, width):
        """Hashes of all substrings of one width."""
        h = self.sums[width:] - self.sums[:-width]
        h *= Rolling.powers[1][: len(h)]
        return self.stirred(h)

    @staticmethod
    def stirred(h):
        import numpy as np

        h ^= h >> np.uint64(31)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(29)
        return h


def mixed(*parts):
    """One 64-bit hash of several integer arrays."""
    import numpy as np

    h = np.zeros(len(parts[0]), np.uint64)
    for x in parts:
        h = (h ^ x.astype(np.uint64)) * np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(32)
    return h


def least_in_windows(values, width):
    """Minimum of each run of width values, from block-wise running minima of both directions."""
    import numpy as np

    n = len(values)
    padded = np.full(-(-n // width) * width, np.iinfo(np.uint64).max, np.uint64)
    padded[:n] = values
    blocks = padded.reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    back = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - width + 1], ahead[width - 1 : n])


def regions_of(data, bounds, depth: int, gram: int):
    """For texts joined to one array, each of depth symbols or more: arrays (text, p, low, high, ah, rid), anchor place, its least and largest place inside the windows it stands for, hashes."""
    import numpy as np

    roll = Rolling(data)
    order = roll.every(gram)
    order >>= np.uint64(32)
    order <<= np.uint64(32)
    order |= np.arange(len(order), dtype=np.uint64)
    # windows that would cross into the next text are left out
    windows = np.diff(bounds) - depth + 1
    text, start = spread(windows)
    start += bounds[text]
    anchor = (least_in_windows(order, depth - gram + 1)[start] & np.uint64(0xFFFFFFFF)).astype(np.int64)
    head = np.flatnonzero(np.r_[True, anchor[1:] != anchor[:-1]])
    first, last = start[head], start[np.r_[head[1:], len(anchor)] - 1]
    p, text = anchor[head], text[head]
    low, high, ah = p - last, p - first, roll.of(p, p + gram)
    return text, p - bounds[text], low, high, ah, mixed(ah, low, high, roll.of(first, last + depth))


def groups_of_blocks(bounds, depth: int, block: int):
    """The texts that have a window, in blocks of block windows at most, as groups of (row, place in the text, begin, end) of about CHUNK symbols."""
    group, held = [], 0
    for row, (begin, end) in enumerate(zip(bounds[:-1].tolist(), bounds[1:].tolist())):
        for at in range(begin, end - depth + 1, block):
            stop = min(end, at + block + depth - 1)
            if held and held + stop - at > CHUNK:
                yield group
                group, held = [], 0
            group.append((row, at - begin, at, stop))
            held += stop - at
    if group:
        yield group


def anchor_rows(docs: DataFrame, depth: int, gram: int, unit: Unit = BYTES, block: int = BLOCK) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in portions(batches, 2):
            k1, k2 = (b.column(i).to_numpy() for i in (0, 1))
            data, bounds = unit.symbols(b.column(2))
            parts = []
            for group in groups_of_blocks(bounds, depth, block):
                row, at, begin, end = np.array(group, np.int64).T
                text, p, *rest = regions_of(np.concatenate([data[x:y] for x, y in zip(begin, end)]), np.r_[0, np.cumsum(end - begin)], depth, gram)
                parts.append((row[text], p + at[text], *rest))
            if parts:
                row, p, low, high, ah, rid = map(np.concatenate, zip(*parts))
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (k1[row], k2[row], p, low.astype(np.int32), high.astype(np.int32), ah.view(np.int64), rid.view(np.int64))], names=[K1, K2, "p", "low", "high", "ah", "rid"])

    return docs.select(K1, K2, F.col("text").cast("binary").alias("text")).mapInArrow(run, f"{K1} long, {K2} long, p long, low int, high int, ah long, rid long")


def carried_schema(unit: Unit) -> str:
    return ", ".join(f"{c} long" for c in unit.carried)


def cut_regions(docs: DataFrame, wanted: DataFrame, depth: int, total: int, unit: Unit) -> DataFrame:
    """The symbols of one occurrence of each wanted region (ah, rid, what is carried, low, high, and its row key and place).

    Copies of a row share its key; each task cuts a key once.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        names, seen = ["ah", "rid", *unit.carried, "low", "high"], set()
        for b in portions(batches, 2):
            new = []
            for key in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                new.append(key not in seen)
                seen.add(key)
            b = b.filter(pa.array(new, pa.bool_()))
            data, bounds = unit.symbols(b.column(2))
            row, todo = listed(b.column(3))
            place = bounds[row] + todo["p"]
            raw, begin, end = data.tobytes(), (place - todo["high"]) * unit.width, (place - todo["low"] + depth) * unit.width
            body = pa.array([raw[x:y] for x, y in zip(begin.tolist(), end.tolist())], pa.binary())
            yield pa.RecordBatch.from_arrays([*(pa.array(todo[c]) for c in names), body], names=[*names, "body"])

    by_row = wanted.groupBy(K1, K2).agg(F.collect_list(F.struct("ah", "rid", *unit.carried, "p", "low", "high")).alias("todo"), F.min("m").alias("copies"))
    texts = docs.select(K1, K2, F.col("text").cast("binary").alias("text"))
    joined = join_hot(texts, by_row, [K1, K2], "copies", total)
    return joined.select(K1, K2, "text", "todo").mapInArrow(run, f"ah long, rid long, {carried_schema(unit)}, low int, high int, body binary")


def stretch_rows(regions: DataFrame, depth: int, unit: Unit) -> DataFrame:
    """Second digit: one row for each stretch of a region, with the hash of what its windows share (core) and of all of it."""
    fixed = ["ah", "rid", *unit.carried]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        step = min(STRETCH, depth)
        for b in portions(batches, "body"):
            low, high = (b.column(c).to_numpy().astype(np.int64) for c in ("low", "high"))
            data, bounds = joined_bytes(b.column("body"))
            roll = Rolling(data.view(unit.dtype))
            row, s = spread(high // step - low // step + 1)
            s += (low // step)[row]
            lo, hi = np.maximum(s * step, low[row]), np.minimum(s * step + step - 1, high[row])
            # the place of the anchor when the window begins where the body does
            top = bounds[row] // unit.width + high[row]
            core = roll.of(top - s * step, top - s * step - step + 1 + depth)
            whole = mixed(lo, hi, roll.of(top - hi, top - lo + depth))
            same = [b.column(c).to_numpy()[row] for c in fixed]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (*same, s.astype(np.int32), lo.astype(np.int32), hi.astype(np.int32), core.view(np.int64), whole.view(np.int64))], names=[*fixed, "s", "lo", "hi", "core", "whole"])

    return regions.select(*fixed, "low", "high", "body").mapInArrow(run, f"ah long, rid long, {carried_schema(unit)}, s int, lo int, hi int, core long, whole long")


def window_rows(regions: DataFrame, opened: DataFrame, depth: int, unit: Unit) -> DataFrame:
    """Last digit: one row for each window of the opened stretches."""
    fixed = ["ah", "rid", *unit.carried]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in portions(batches, "body"):
            high = b.column("high").to_numpy().astype(np.int64)
            data, bounds = joined_bytes(b.column("body"))
            roll = Rolling(data.view(unit.dtype))
            owner, spans = listed(b.column("spans"))
            span, o = spread(spans["hi"] - spans["lo"] + 1)
            o += spans["lo"][span]
            row = owner[span]
            start = bounds[row] // unit.width + high[row] - o
            same = [b.column(c).to_numpy()[row] for c in fixed]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (*same, o.astype(np.int32), roll.of(start, start + depth).view(np.int64))], names=[*fixed, "o", "wh"])

    todo = opened.groupBy("ah", "rid").agg(F.collect_set(F.struct("lo", "hi")).alias("spans"))
    return regions.join(todo, ["ah", "rid"]).select(*fixed, "high", "body", "spans").mapInArrow(run, f"ah long, rid long, {carried_schema(unit)}, o int, wh long")


def repeated_ranges(docs: DataFrame, depth: int = DEPTH, gram: int = GRAM, unit: Unit = BYTES, block: int = BLOCK) -> DataFrame:
    """For docs with a row key: rows (key, ranges, n), the ranges [start, end) of all repeated windows in symbols; n rows have the key."""
    spark, fixed = docs.sparkSession, ["ah", "rid", *unit.carried]
    every = materialise(anchor_rows(docs, depth, gram, unit, block), "repeats-anchors")
    total = every.count()
    # the first digit drops most: anchors met once (or in one document) stand for no repeated window
    met = every.groupBy("ah").agg(*unit.first(), (F.min("rid") != F.max("rid")).alias("alike")).filter(unit.repeated)
    anchors = materialise(join_hot(every, met.select("ah", "alike", F.col("m").alias("n")), ["ah"], "n", total).drop("n"), "repeats-met")
    discard(every)
    release(spark)
    distinct = anchors.groupBy("ah", "rid").agg(*unit.first(), *(F.first(c).alias(c) for c in (K1, K2, "p", "low", "high", "alike")))
    held = materialise(distinct.withColumn("whole", F.expr(unit.repeated)).filter("alike OR whole"), "repeats-regions")
    release(spark)
    regions = materialise(cut_regions(docs, held.filter("alike"), depth, total, unit), "repeats-bodies")
    release(spark)
    dealt = materialise(stretch_rows(regions, depth, unit), "repeats-dealt")
    same = dealt.groupBy("ah", "s", "core").agg(*unit.merged(), (F.min("whole") == F.max("whole")).alias("one"), F.count("*").alias("n")).filter(unit.repeated)
    stretches = join_hot(dealt, same.select("ah", "s", "core", "one", "n"), ["ah", "s", "core"], "n", dealt.count())
    stretches = materialise(stretches.withColumn("settled", F.expr(unit.repeated)).select(*fixed, "lo", "hi", "one", "settled"), "repeats-stretches")
    discard(dealt)
    windows = materialise(window_rows(regions, stretches.filter("NOT one"), depth, unit), "repeats-windows")
    equal = windows.groupBy("ah", "o", "wh").agg(*unit.merged(), F.count("*").alias("n")).filter(unit.repeated).select("ah", "o", "wh", "n")
    alone = join_hot(windows.filter(f"NOT ({unit.repeated})"), equal, ["ah", "o", "wh"], "n", windows.count())
    found = alone.select("ah", "rid", "m", F.col("o").alias("lo"), F.col("o").alias("hi")).unionByName(stretches.filter("one AND NOT settled").select("ah", "rid", "m", "lo", "hi"))
    partly = found.groupBy("ah", "rid").agg(F.first("m").alias("m"), F.collect_set(F.struct("lo", "hi")).alias("spans"))
    wholly = held.filter("whole").select("ah", "rid", "m", F.array(F.struct(F.col("low").alias("lo"), F.col("high").alias("hi"))).alias("spans"))
    result = materialise(partly.unionByName(wholly), "repeats-result")
    release(spark)
    discard(windows, regions, stretches, held)
    hits = join_hot(anchors.select(K1, K2, "p", "ah", "rid"), result, ["ah", "rid"], "m", total)
    ranges = F.transform("spans", lambda x: F.struct((F.col("p") - x["hi"]).alias("s"), (F.col("p") - x["lo"] + depth).alias("e")))
    # copies of a row have the same anchors, so a set of what the anchors give holds each once
    by_row = hits.select(K1, K2, ranges.alias("r")).groupBy(K1, K2).agg(F.collect_set("r").alias("r"), F.count("*").alias("n"))
    done = materialise(by_row.select(K1, K2, F.flatten("r").alias("ranges"), F.ceil(F.col("n") / F.size("r")).alias("n")), "repeats-ranges")
    discard(anchors, result)
    return done


def merged(ranges):
    """Maximal runs of a column of lists of ranges: arrays (row, start, end), in order."""
    import numpy as np

    row, fields = listed(ranges)
    if not len(row):
        return (np.zeros(0, np.int64),) * 3
    apart = int(fields["e"].max()) + 1  # rows lie so far from each other that none meet
    order = np.argsort(row * apart + fields["s"], kind="stable")
    s, e = (row * apart + fields["s"])[order], np.maximum.accumulate((row * apart + fields["e"])[order])
    head = np.flatnonzero(np.r_[True, s[1:] > e[:-1]])
    s, e = s[head], e[np.r_[head[1:], len(e)] - 1]
    row = s // apart
    return row, s - row * apart, e - row * apart


def shared_passages(docs: DataFrame, words: int = PASSAGE, gram: int = PASSAGE_GRAM, block: int = BLOCK) -> DataFrame:
    """For docs with a row key: rows (key, ranges, n), the ranges of words in passages of words or more that another document has too."""
    return repeated_ranges(docs, words, gram, WORDS, block)


def without_repeats(docs: DataFrame, depth: int = DEPTH, gram: int = GRAM, passage: int = PASSAGE, passage_gram: int = PASSAGE_GRAM, block: int = BLOCK) -> DataFrame:
    """Rows (doc_id, n_bytes, n_removed, n_spans, kept, n_passage_words): the remaining bytes, which may cut a character where a window does; the words in shared passages, which stay."""
    spark = docs.sparkSession
    bounded_batches(spark)
    keyed = with_row_key(docs.select("doc_id", "text"))
    ranges = repeated_ranges(keyed, depth, gram, BYTES, block).withColumnRenamed("n", "n_rows")
    shared = shared_passages(keyed, passage, passage_gram, block).select(K1, K2, F.col("ranges").alias("passages"), F.col("n").alias("n_shared"))
    either = ranges.join(shared, [K1, K2], "full").withColumn("n", F.coalesce("n_rows", "n_shared"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in portions(batches, 1):
            data, bounds = joined_bytes(b.column(1))
            n, sizes = b.num_rows, np.diff(bounds)
            row, s, e = merged(b.column(2))
            removed, spans = (np.bincount(row, x, n).astype(np.int64) for x in (e - s, np.ones(len(row))))
            turns = np.zeros(len(data) + 1, np.int32)
            turns[bounds[row] + s] += 1
            np.subtract.at(turns, bounds[row] + e, 1)  # one text's run may end where the next one's begins
            kept = data[np.cumsum(turns[:-1]) == 0] if len(row) else data
            ends = np.r_[0, np.cumsum(sizes - removed)].astype(np.int32)
            left = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(kept))])
            row, s, e = merged(b.column(3))
            shared = np.bincount(row, e - s, n).astype(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), *map(pa.array, (sizes, removed, spans)), left, pa.array(shared)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept", "n_passage_words"])

    texts = keyed.select(K1, K2, "doc_id", F.col("text").cast("binary").alias("text"))
    joined = join_hot(texts, either.select(K1, K2, "ranges", "passages", "n"), [K1, K2], "n", max(1, keyed.count()), how="left")
    kind = docs.schema["doc_id"].dataType.simpleString()
    return joined.select("doc_id", "text", "ranges", "passages").mapInArrow(run, f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, kept binary, n_passage_words long")


def op2_repeated_windows(spark, sf_dir: str) -> DataFrame:
    """Every byte under a 400-byte string that starts twice or more goes; per document, what is left, and its words in passages of over 50 words that other documents share."""
    done = without_repeats(read_table(spark, sf_dir, "documents"))
    return done.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"), "n_passage_words")
