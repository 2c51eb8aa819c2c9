"""Near-duplicate groups by SimHash links and, for looser copies, verified Jaccard similarity of word shingles.

Fingerprints within two bits link through the popcount grid of ``simhash``. Copies with similarity 0.8 differ in ten bits and more,
beyond what any grid can separate from chance, so the same shingle hashes also give bands of minimum hashes; documents that
share a band are compared on their whole shingle sets. Texts with equal sets are one node.

Bands of at most ``pair_limit`` nodes are compared in full. Larger ones are compared with two leaders (the node that meets
most others, and a random one); of the nodes like neither, one for each leader linked to elsewhere is dealt again by further minimum hashes, three ways each, level
by level, so dissimilar texts that share a frequent passage separate without ever being paired. That only merges early: what
large bands still hold of different components goes through an exact set join on prefixes of rare shingles, so a pair that
shares a band, however crowded, is never lost. A pair of similarity 0.8 shares one of the 20 bands with probability 0.9996.
Links are exact on whole sets of 32-bit shingle hashes (no similarity is estimated, and two sets of 10,000 shingles share 0.02 by a hash's chance); of recall
only the bands are by chance.

Edge cases: texts without words form one group; shorter texts are one shingle; of rows that are equal in doc_id and text one
stays; a null doc_id comes after all others; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trilist.llm.common import K1, K2, bounded_batches, components, discard, join_dealt, join_hot, materialise, packed, release
from trilist.llm.simhash import links

BANDS, ROWS, LEVELS, WAYS, PAIR_LIMIT = 20, 5, 2, 3, 4
HOT_SHARE = 0.001
BLOCK = 1024


def shingle_hashes(text: str | None, width: int):
    """XXH64 of all word shingles, repeats included."""
    from itertools import repeat

    import numpy as np
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if len(words) < width:
        parts = iter([b" ".join(words)] if words else [])
    else:
        parts = map(b" ".join, zip(*(words[i:] for i in range(width))))
    return np.fromiter(map(xxhash.xxh64_intdigest, parts, repeat(42)), np.uint64)


def sketches(docs: DataFrame, width: int) -> DataFrame:
    """For docs with a row key: key, doc_id, fp, node (hash of the shingle set), bands and spare minimum hashes."""
    total = BANDS * ROWS + LEVELS * WAYS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np
        import xxhash

        rng = np.random.default_rng(7)
        factors, offsets = rng.integers(0, 2**63, total, dtype=np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 2**63, total, dtype=np.uint64)
        for b in batches:
            hashes = [shingle_hashes(t, width) for t in b.column(3).to_pylist()]
            fps, nodes, bands, spare = [], [], [], []
            for h in hashes:
                nodes.append(xxhash.xxh3_128_hexdigest(np.unique(h).tobytes()))
                if not len(h):
                    fps.append(0)
                    bands.append(None)
                    spare.append(None)
                    continue
                ones = np.zeros(64, np.int64)
                least = np.full(total, np.iinfo(np.uint64).max)
                for at in range(0, len(h), 1 << 15):
                    part = h[at : at + (1 << 15)]
                    ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
                    for k in range(total):
                        least[k] = min(least[k], (part * factors[k] + offsets[k]).min())
                fps.append(int(np.packbits(ones * 2 > len(h), bitorder="little").view(np.int64)[0]))
                bands.append([xxhash.xxh64_intdigest(least[k : k + ROWS].tobytes(), k) - 2**63 for k in range(0, BANDS * ROWS, ROWS)])
                spare.append((least[BANDS * ROWS :] >> np.uint64(1)).astype(np.int64).tolist())
            longs = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(fps, pa.int64()), pa.array(nodes, pa.string()), pa.array(bands, longs), pa.array(spare, longs)], names=[K1, K2, "doc_id", "fp", "node", "bands", "spare"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select(K1, K2, "doc_id", "text").mapInArrow(run, f"{K1} long, {K2} long, doc_id {kind}, fp long, node string, bands array<long>, spare array<long>")


def shingle_sets(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """Rows (node, items): the sorted distinct shingle hashes, 32 bits each, of one document of each wanted node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            sets = [np.unique((shingle_hashes(t, width) >> np.uint64(32)).astype(np.uint32)).tobytes() for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sets, pa.binary())], names=["node", "items"])

    joined = docs.select(K1, K2, "text").join(wanted, [K1, K2])
    return joined.select("node", "text").mapInArrow(run, "node string, items binary")


def similar_pairs(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The rows of pairs(a, b) whose sets have at least that Jaccard similarity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            keep = []
            for x, y in zip(b.column(2), b.column(3)):
                p, q = (np.frombuffer(v.as_buffer(), np.uint32) for v in (x, y))
                both = len(np.intersect1d(p, q, assume_unique=True))
                keep.append(both >= similarity * (len(p) + len(q) - both))
            yield b.filter(pa.array(keep, pa.bool_())).select(["a", "b"])

    total = max(1, pairs.count())
    full = join_dealt(pairs, sets.select(F.col("node").alias("a"), F.col("items").alias("x")), "a", total)
    full = join_dealt(full, sets.select(F.col("node").alias("b"), F.col("items").alias("y")), "b", total, pairs)
    return full.select("a", "b", "x", "y").mapInArrow(run, "a string, b string")


def shingle_rows(sets: DataFrame) -> DataFrame:
    """Rows (node, size, t): one for each shingle hash of each set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        def batch(names, found):
            at = np.repeat(np.arange(len(found)), [len(t) for t in found])
            sizes = np.array([len(t) for t in found], np.int64)[at]
            return pa.RecordBatch.from_arrays([pa.array(names, pa.string()).take(pa.array(at)), pa.array(sizes), pa.array(np.concatenate(found).astype(np.int64))], names=["node", "size", "t"])

        for b in batches:
            names, found = [], []
            for name, items in zip(b.column(0).to_pylist(), b.column(1)):
                names.append(name)
                found.append(np.frombuffer(items.as_buffer(), np.uint32))
                if sum(map(len, found)) > 1 << 16:
                    yield batch(names, found)
                    names, found = [], []
            if found:
                yield batch(names, found)

    return sets.select("node", "items").mapInArrow(run, "node string, size long, t long")


def crowded_links(crowded: DataFrame, sets: DataFrame, roots: DataFrame, similarity: float) -> DataFrame | None:
    """All edges (a, b) of at least that similarity between nodes of different roots that share a crowded band (g, node).

    Sets that similar share one of their first size - ceil(similarity * size) + 1 shingles in any common order; here the rare
    come first, so a frequent passage makes no pairs. Members of one root need no edge: of each shingle's nodes,
    those outside its most frequent root meet the others. None where no crowded band has two roots.
    """
    named = materialise(crowded.select("g", "node").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node")), "similar-named", "snappy")
    mixed = named.groupBy("g").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count("*").alias("n")).filter("lo <> hi").select("g", "n")
    mine = materialise(join_hot(named, mixed, ["g"], "n", max(1, named.count())).select("node", "root").distinct(), "similar-open", "snappy")
    if mine.isEmpty():
        return None
    rows = materialise(shingle_rows(sets.join(mine.select("node"), "node", "left_semi")), "similar-shingles")
    often = materialise(rows.groupBy("t").agg(F.count("*").alias("n")).filter("n > 1"), "similar-often", "snappy")
    total = rows.count()
    place = F.row_number().over(Window.partitionBy("node").orderBy(F.coalesce("n", F.lit(1)), "t"))
    most = F.col("size") - F.ceil(F.col("size") * similarity - 1e-9) + 1
    # at most 1/HOT_SHARE shingles are in more than that share of the rows: they come last in the order, by t, and need no join
    limit = max(1, int(total * HOT_SHARE))
    hot = [r.t for r in often.filter(F.col("n") > limit).select("t").collect()]
    is_hot = F.col("t").isin(hot) if hot else F.lit(False)
    seldom = rows.filter(~is_hot).join(often.filter(F.col("n") <= limit), "t", "left")
    ordered = seldom.unionByName(rows.filter(is_hot).withColumn("n", F.lit(total).cast("long")))
    first = ordered.withColumn("place", place).filter((F.col("place") <= most) & F.col("n").isNotNull())
    # each row has its whole prefix in the common order, so that a pair meets at the first shingle it shares and at no other
    prefixes = first.groupBy("node").agg(F.transform(F.array_sort(F.collect_list(F.struct("place", "t"))), lambda x: x["t"]).alias("prefix"))
    first = materialise(first.select("t", "node", "size", "place").join(prefixes, "node").join(mine, "node"), "similar-prefixes")
    held = first.groupBy("t", "root").agg(F.count("*").alias("c")).groupBy("t").agg(F.max_by("root", F.struct("c", "root")).alias("main"), F.sum("c").alias("m"), (F.sum("c") - F.max("c")).alias("beside"), F.count("*").alias("roots"))
    held = materialise(held.filter("roots > 1").select("t", "main", "m", "beside"), "similar-mixed", "snappy")
    met = materialise(join_hot(first, held, ["t"], "m", max(1, first.count())), "similar-met")
    # a shingle's nodes meet in blocks of BLOCK by BLOCK, each node copied once a block of the other side: up to BLOCK nodes none is copied
    across, down = F.ceil(F.col("beside") / BLOCK).cast("int"), F.ceil(F.col("m") / BLOCK).cast("int")
    every, dealt = lambda n: F.explode(F.sequence(F.lit(0), n - 1)), lambda n: F.pmod(F.xxhash64("node", "t"), n).cast("int")
    a = met.filter("root <> main").withColumn("i", dealt(across)).withColumn("j", every(down))
    a = a.select("t", "i", "j", F.col("node").alias("a"), F.col("root").alias("ra"), F.col("size").alias("sa"), F.col("place").alias("pa"), F.col("prefix").alias("xa"))
    b = met.withColumn("j", dealt(down)).withColumn("i", every(across))
    b = b.select("t", "i", "j", F.col("node").alias("b"), F.col("root").alias("rb"), F.col("size").alias("sb"), F.col("place").alias("pb"), F.col("prefix").alias("xb"), (F.col("root") == F.col("main")).alias("mainly"))
    # what precedes the first shared shingle is not shared, and of what follows no more than the shorter rest can be
    most = 1 + F.least(F.col("sa") - F.col("pa"), F.col("sb") - F.col("pb"))
    enough = most >= (F.col("sa") + F.col("sb")) * (similarity / (1 + similarity)) - 1e-9
    sizes = (F.col("sa") >= F.col("sb") * similarity - 1e-9) & (F.col("sb") >= F.col("sa") * similarity - 1e-9)
    both = a.join(b, ["t", "i", "j"]).filter("ra <> rb AND (mainly OR a < b)").filter(sizes & enough & (F.array_intersect("xa", "xb")[0] == F.col("t")))
    likely = both.select(F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y")).distinct()
    asked = materialise(likely.select(F.col("x").alias("a"), F.col("y").alias("b")), "similar-crowded", "snappy")
    good = materialise(similar_pairs(asked, sets, similarity), "similar-crowded-links", "snappy")
    discard(named, mine, rows, often, first, held, met, asked)
    return good


def band_links(docs: DataFrame, nodes: DataFrame, width: int, similarity: float) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Edges (a, b) between nodes(node, lead, bands, spare) of at least that similarity that share a band; the crowded bands (g, node), whose edges may be too few; and the sets."""
    one = nodes.filter("bands IS NOT NULL").select("node", F.posexplode("bands").alias("band", "key")).select("node", F.xxhash64("band", "key").alias("g"))
    meet = one.groupBy("g").agg(F.count("*").alias("size")).filter("size > 1")
    groups = materialise(join_hot(one, meet, ["g"], "size", one.count()), "similar-groups", "snappy")
    wanted = groups.select("node").distinct().join(nodes.select("node", "lead.k1", "lead.k2"), "node").select("node", F.col("k1").alias(K1), F.col("k2").alias(K2))
    sets = materialise(shingle_sets(docs, wanted, width), "similar-sets").groupBy("node").agg(F.first("items").alias("items"))
    release(docs.sparkSession)
    rank = nodes.select("node", "spare")
    busy = materialise(groups.groupBy("node").agg(F.sum("size").alias("meets")), "similar-busy", "snappy")
    crowded = groups.filter(F.col("size") > PAIR_LIMIT)
    crowded._scratch_path = groups._scratch_path
    found = None
    for level in range(LEVELS + 1):
        small = groups.filter(F.col("size") <= PAIR_LIMIT)
        pairs = small.select("g", F.col("node").alias("a")).join(small.select("g", F.col("node").alias("b")), "g").filter("a < b").select("a", "b")
        large = groups.filter(F.col("size") > PAIR_LIMIT)
        leaders = large.join(busy, "node").groupBy("g").agg(F.max_by("node", F.struct("meets", "node")).alias("l1"), F.min_by("node", F.struct(F.xxhash64("g", "node"), "node")).alias("l2"), F.count("*").alias("n"))
        leaders = materialise(leaders, f"similar-leaders-{level}", "snappy")
        led = materialise(join_hot(large.select("g", "node"), leaders, ["g"], "n", max(1, large.count())), f"similar-led-{level}", "snappy")
        tries = led.select("g", "node", F.explode(F.array("l1", "l2")).alias("l")).filter("node <> l")
        asked = materialise(pairs.unionByName(tries.select(F.least("node", "l").alias("a"), F.greatest("node", "l").alias("b"))).distinct(), f"similar-asked-{level}", "snappy")
        good = materialise(similar_pairs(asked, sets, similarity), f"similar-links-{level}", "snappy")
        found = good if found is None else found.unionByName(good)
        if level == LEVELS:
            break
        linked = tries.join(good.unionByName(good.select(F.col("b").alias("a"), F.col("a").alias("b"))).select(F.col("a").alias("node"), F.col("b").alias("l")), ["node", "l"], "left_semi").select("g", "node")
        rest = led.filter("node <> l1 AND node <> l2").select("g", "node").join(linked.distinct(), ["g", "node"], "left_anti")
        # nodes linked to the same leader need no more links among themselves: one speaks for them in each group
        ends = good.unionByName(good.select(F.col("b").alias("a"), F.col("a").alias("b"))).groupBy(F.col("a").alias("node")).agg(F.min("b").alias("to"))
        rest = rest.join(ends, "node", "left").groupBy("g", F.least("node", F.coalesce("to", "node")).alias("to")).agg(F.min_by("node", F.struct(F.xxhash64("g", "node"), "node")).alias("node"))
        ways = F.transform(F.sequence(F.lit(0), F.lit(WAYS - 1)), lambda i: F.xxhash64("g", i, F.get("spare", i + level * WAYS)))
        again = materialise(rest.join(rank, "node").select("node", F.explode(ways).alias("g")), f"similar-again-{level}", "snappy")
        spent = [*([groups] if level else []), leaders, led, asked, again]
        groups = materialise(again.join(again.groupBy("g").agg(F.count("*").alias("size")).filter("size > 1"), "g").select("g", "node", "size"), f"similar-next-{level}", "snappy")
        discard(*spent)
        if groups.isEmpty():
            break
    return found, crowded, sets


def near_duplicates(docs: DataFrame, width: int = 5, similarity: float = 0.8) -> DataFrame:
    """Rows (doc, stays): whole rows of docs as structs; of each group of near-duplicates the smallest doc_id stays."""
    bounded_batches(docs.sparkSession)
    rows = packed(docs, "doc_id", "text")
    plain = rows.select(K1, K2, "doc_id", "text")
    sketch = materialise(sketches(plain, width), "similar-sketches")
    order = F.struct(F.col("doc_id").isNull().alias("nul"), F.col("doc_id").alias("id"), F.col(K1).alias("k1"), F.col(K2).alias("k2"))
    nodes = materialise(sketch.groupBy("node").agg(F.min(order).alias("lead"), F.first("fp").alias("fp"), F.first("bands").alias("bands"), F.first("spare").alias("spare")), "similar-nodes")
    release(docs.sparkSession)
    heads = materialise(nodes.groupBy("fp").agg(F.min("node").alias("head"), F.count("*").alias("n")), "similar-heads", "snappy")
    same = nodes.join(heads.filter("n > 1"), "fp").select(F.col("head").alias("a"), F.col("node").alias("b")).filter("a <> b")
    close = links(heads.select("fp"))
    close = close.join(heads.select(F.col("fp").alias("a"), F.col("head").alias("x")), "a").join(heads.select(F.col("fp").alias("b"), F.col("head").alias("y")), "b").select(F.col("x").alias("a"), F.col("y").alias("b"))
    linked, crowded, sets = band_links(plain, nodes, width, similarity)
    roots = components(same.unionByName(close).unionByName(linked), "similar-components")
    more = crowded_links(crowded, sets, roots, similarity)
    discard(crowded)
    if more is not None and not more.isEmpty():
        early, roots = roots, components(more.unionByName(roots.select(F.col("node").alias("a"), F.col("root").alias("b"))), "similar-components")
        discard(early)
    rooted = nodes.select("node", "lead").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    keep = rooted.groupBy("root").agg(F.min("lead").alias("lead")).select(F.col("lead.k1").alias(K1), F.col("lead.k2").alias(K2), F.lit(True).alias("stays"))
    keep = materialise(keep, "similar-keep", "snappy")
    discard(sketch, nodes, heads, roots)
    release(docs.sparkSession)
    # rows with equal keys are equal in doc_id and text: the join brings them together, and one of them stays
    first = F.row_number().over(Window.partitionBy(K1, K2).orderBy(F.lit(0))) == 1
    return rows.select("doc", K1, K2).join(keep, [K1, K2], "left").select("doc", (F.coalesce("stays", F.lit(False)) & first).alias("stays"))
