"""SimHash near-dedup on a grid of segment popcounts.

A 64-bit fingerprint maps to the bit counts of its 32 two-bit segments. The Manhattan distance of two such vectors never
exceeds the Hamming distance of the fingerprints, so a range join of radius 2 under it loses no link. The grid: segments
form four blocks; vectors within distance 2 agree on two blocks at least, so a cell is a pair of blocks with its counts,
and each fingerprint lies in six cells. Inside a cell, pairs within Manhattan distance 2 are verified on all 64 bits.

Fingerprints of cells with more than ``cell_limit`` go to a finer grid: eight blocks, of which vectors within distance 2
agree on six at least, so a cell is six blocks with their counts and each fingerprint lies in 28. Cells that are still over
the limit are not paired: there, fingerprints meet at the points within one bit of
them (two fingerprints differ in at most two bits exactly if they share such a point; at most 65 meet at one), which links
the same pairs in linear work. Equal fingerprints are one node, so copies are never paired.

Edge cases: null or wordless text has fingerprint 0 and is linked like any other; shorter texts are one shingle; a null
doc_id is never a component's name unless all are null; equal rows get equal results; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.llm.common import bounded_batches, components, discard, join_hot, materialise, read_table

RADIUS, CELL_LIMIT = 2, 64
LOW_BITS = 0x5555555555555555


def fingerprint(text: str | None, width: int) -> int:
    """SimHash over the XXH64 (seed 42) of word shingles; words are runs of bytes other than ASCII white space."""
    from itertools import repeat

    import numpy as np
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) < width:
        shingles = iter([b" ".join(words)])
    else:
        shingles = map(b" ".join, zip(*(words[i:] for i in range(width))))
    total, ones = 0, np.zeros(64, np.int64)
    hashes = np.fromiter(map(xxhash.xxh64_intdigest, shingles, repeat(42)), np.uint64)
    for at in range(0, len(hashes), 1 << 16):
        part = hashes[at : at + (1 << 16)]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        total += len(part)
    return int(np.packbits(ones * 2 > total, bitorder="little").view(np.int64)[0])


def fingerprints(docs: DataFrame, keys: list[str], width: int) -> DataFrame:
    """The key columns and fp, a signed long with the 64 bits."""
    bounded_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = pa.array([fingerprint(t, width) for t in b.column(len(keys)).to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keys)], found], names=[*keys, "fp"])

    schema = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in keys) + ", fp long"
    return docs.select(*keys, "text").mapInArrow(run, schema)


def grid(fps: DataFrame, blocks: int, agree: int) -> DataFrame:
    """Rows (fp, v, pick, cell): each fingerprint's segment counts v and its cells, one for each choice of agreeing blocks."""
    low, width = F.lit(LOW_BITS), 64 // blocks
    odd = F.shiftrightunsigned("fp", 1)
    both, one = F.col("fp").bitwiseAND(odd).bitwiseAND(low), F.col("fp").bitwiseXOR(odd).bitwiseAND(low)
    counts = F.shiftleft(both, 1).bitwiseOR(one)  # 0, 1 or 2 in each two-bit field
    masks = [sum(((1 << width) - 1) << width * i for i in chosen) for chosen in combinations(range(blocks), agree)]
    cells = F.array(*(F.struct(F.lit(k).alias("pick"), F.col("v").bitwiseAND(F.lit(m - 2**64 if m >= 2**63 else m)).alias("cell")) for k, m in enumerate(masks)))
    return fps.select("fp", counts.alias("v")).select("fp", "v", F.explode(cells).alias("c")).select("fp", "v", "c.pick", "c.cell")


def met_in_cells(fps: DataFrame, blocks: int, agree: int, cell_limit: int) -> tuple[DataFrame, DataFrame]:
    """Verified edges (a, b) of the cells within the limit, and the fingerprints (fp) of the others."""
    cells = materialise(grid(fps, blocks, agree), "simhash-cells", "snappy")
    full = cells.groupBy("pick", "cell").agg(F.count("*").alias("n")).filter("n > 1")
    shared = materialise(join_hot(cells, full, ["pick", "cell"], "n", cells.count()), "simhash-shared", "snappy")
    discard(cells)
    left = shared.filter(F.col("n") <= cell_limit).select("pick", "cell", F.col("fp").alias("a"), F.col("v").alias("va"))
    right = shared.filter(F.col("n") <= cell_limit).select("pick", "cell", F.col("fp").alias("b"), F.col("v").alias("vb"))
    apart = F.expr(" + ".join(f"abs((shiftrightunsigned(va, {s}) & 3) - (shiftrightunsigned(vb, {s}) & 3))" for s in range(0, 64, 2)))
    near = left.join(right, ["pick", "cell"]).filter((F.col("a") < F.col("b")) & (apart <= RADIUS)).select("a", "b")
    exact = near.filter(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= RADIUS)
    return exact, shared.filter(F.col("n") > cell_limit).select("fp").distinct()


def links_by_path(fps: DataFrame, cell_limit: int = CELL_LIMIT) -> DataFrame:
    """Edges (a, b, path) between different fingerprints that connect all those within two bits of each other; path: grid, finer or points."""
    coarse, crowded = met_in_cells(fps, 4, 2, cell_limit)
    finer, full = met_in_cells(materialise(crowded, "simhash-crowded", "snappy"), 8, 6, cell_limit)
    flips = [F.col("fp")] + [F.col("fp").bitwiseXOR(F.lit((1 << i) - (1 << 64 if i == 63 else 0))) for i in range(64)]
    points = full.select("fp", F.explode(F.array(*flips)).alias("point")).groupBy("point").agg(F.collect_set("fp").alias("at")).filter(F.size("at") > 1)
    star = points.select(F.array_min("at").alias("a"), F.explode("at").alias("b")).filter("a <> b")
    named = [x.withColumn("path", F.lit(p)) for x, p in ((coarse, "grid"), (finer, "finer"), (star, "points"))]
    return named[0].unionByName(named[1]).unionByName(named[2])


def links(fps: DataFrame, cell_limit: int = CELL_LIMIT) -> DataFrame:
    """Edges (a, b) between different fingerprints that connect all those within two bits of each other."""
    return links_by_path(fps, cell_limit).select("a", "b").distinct()


def group_by_fingerprint(fps: DataFrame, order: str, cell_limit: int = CELL_LIMIT) -> DataFrame:
    """For a table with fp and an id column: rows (fp, n, lead) where lead is the smallest id of the whole component."""
    nodes = materialise(fps.groupBy("fp").agg(F.min(order).alias("own"), F.count("*").alias("n")), "simhash-nodes", "snappy")
    roots = components(links(nodes.select("fp"), cell_limit), "simhash-components")
    rooted = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    leads = rooted.groupBy("root").agg(F.min("own").alias("lead"))
    return rooted.join(leads, "root").select("fp", "n", "lead")


def simhash_paths(spark, sf_dir: str) -> DataFrame:
    """How many different links each path of the grid gives: (path, n_links)."""
    fps = materialise(fingerprints(read_table(spark, sf_dir, "documents"), ["doc_id"], 3).select("fp").distinct(), "simhash-fingerprints")
    return links_by_path(fps).distinct().groupBy("path").agg(F.count("*").alias("n_links"))


def op4_simhash_grid(spark, sf_dir: str) -> DataFrame:
    """Components of documents whose 3-word SimHash fingerprints differ in two bits or fewer."""
    fps = materialise(fingerprints(read_table(spark, sf_dir, "documents"), ["doc_id"], 3), "simhash-fingerprints")
    groups = materialise(group_by_fingerprint(fps, "doc_id"), "simhash-groups")
    done = join_hot(fps, groups, ["fp"], "n", fps.count())
    return done.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.col("lead").alias("component_id"))
