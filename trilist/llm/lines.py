"""Line dedup: cross-site boilerplate by distinct-site spread, with DataFrame functions only.

Sketches: each task folds the sites of a line hash into a HyperLogLog sketch, and sketches of the same line merge in the
aggregation, so a line on a third of all rows costs one sketch per task. Lines whose estimate is within ``band`` of the
threshold get an exact distinct count; the others are decided by the sketch. A boilerplate line stays only at its first
occurrence (smallest doc_id, nulls last, then smallest line number); repeated rows with that doc_id all keep it.

Edge cases: null text has no lines and stays null; lines shorter than ``min_chars`` after trimming (blank ones too) are never
boilerplate; a null site counts as one site; equal rows get equal results; an empty table gives no rows; other columns
pass through untouched.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trilist.llm.common import K1, K2, join_hot, materialise, packed, read_table

MIN_SITES, MIN_CHARS, LG_K = 10, 16, 10
LINE = ["lh", "lh2"]


def trimmed(line: Column) -> Column:
    return F.trim(line, F.lit(" \t\r"))


def occurrences(docs: DataFrame, site: str, min_chars: int) -> DataFrame:
    """One row for each line long enough: row key, doc_id, line number, line hash (128 bits in two columns), site hash."""
    lines = packed(docs, "doc_id", "text", site).select(K1, K2, "doc_id", F.xxhash64(F.col(site), F.col(site).isNull()).alias("site"), F.posexplode(F.split(F.col("text"), "\n")).alias("pos", "line"))
    norm = trimmed(F.col("line"))
    return lines.filter(F.length(norm) >= min_chars).select(K1, K2, "doc_id", "pos", F.xxhash64(norm).alias("lh"), F.xxhash64(F.lit("second"), norm).alias("lh2"), "site")


def boilerplate(occ: DataFrame, min_sites: int, lg_k: int = LG_K, band: float | None = None) -> DataFrame:
    """Lines (lh, lh2, n, first) on min_sites sites or more; n counts occurrences, first is the one that stays."""
    width = band if band is not None else max(0.2, 4 * 1.04 / math.sqrt(2**lg_k))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("nul"), F.col("doc_id").alias("id"), F.col("pos").alias("at"))).alias("first")
    spread = occ.groupBy(*LINE).agg(F.hll_sketch_agg("site", F.lit(lg_k)).alias("sketch"), F.count("*").alias("n"), first).filter(F.col("n") >= min_sites)
    rated = materialise(spread.withColumn("sites", F.hll_sketch_estimate("sketch")).filter(F.col("sites") >= min_sites * (1 - width)).drop("sketch"), "line-spread")
    sure = rated.filter(F.col("sites") > min_sites * (1 + width)).select(*LINE, "n", "first")
    near = rated.filter(F.col("sites") <= min_sites * (1 + width))
    total = rated.agg(F.sum("n")).first()[0] or 0
    pairs = join_hot(occ.select(*LINE, "site"), near.select(*LINE, "n"), LINE, "n", total).groupBy(*LINE, "site").agg(F.lit(1).alias("one"))
    exact = pairs.groupBy(*LINE).agg(F.count("*").alias("exact")).filter(F.col("exact") >= min_sites)
    return sure.unionByName(near.join(exact.select(*LINE), LINE, "left_semi").select(*LINE, "n", "first"))


def removed_lines(docs: DataFrame, site: str = "source", min_sites: int = MIN_SITES, min_chars: int = MIN_CHARS, lg_k: int = LG_K) -> DataFrame:
    """Rows (row key, gone): the numbers of the lines to remove; only for rows of docs that lose lines."""
    occ = materialise(occurrences(docs, site, min_chars), "line-occurrences")
    common = materialise(boilerplate(occ, min_sites, lg_k), "line-boilerplate")
    total = common.agg(F.sum("n")).first()[0] or 0
    hits = join_hot(occ.select(K1, K2, "doc_id", "pos", *LINE), common, LINE, "n", total)
    later = hits.filter(~(F.col("doc_id").eqNullSafe(F.col("first.id")) & (F.col("pos") == F.col("first.at"))))
    return later.groupBy(K1, K2).agg(F.collect_set("pos").alias("gone"))


def dedup_lines(docs: DataFrame, **options) -> DataFrame:
    """Rows (doc, text, n_lines, n_gone): the row of docs as a struct, its shortened text, how many lines it had and lost."""
    joined = packed(docs, "text").join(removed_lines(docs, **options), [K1, K2], "left")
    lines = F.split(F.col("text"), "\n")
    kept = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("gone"))
    text = F.when(F.col("gone").isNull(), F.col("text")).otherwise(F.array_join(F.transform(kept, lambda i: F.get(lines, i)), "\n"))
    n_lines = F.when(F.col("text").isNull(), F.lit(0)).otherwise(F.length("text") - F.length(F.replace(F.col("text"), F.lit("\n"), F.lit(""))) + 1)
    return joined.select("doc", text.alias("text"), n_lines.cast("long").alias("n_lines"), F.when(F.col("gone").isNull(), F.lit(0)).otherwise(F.size("gone")).cast("long").alias("n_gone"))


def op1_line_spread(spark, sf_dir: str) -> DataFrame:
    """Boilerplate on ten sites or more goes from all documents but its first; per document, what is left."""
    done = dedup_lines(read_table(spark, sf_dir, "documents"))
    return done.select("doc.doc_id", "n_lines", F.col("n_gone").alias("n_removed"), F.coalesce(F.length("text"), F.lit(0)).cast("long").alias("kept_chars"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


OP1_SQL = rf"""
WITH lines AS (
  SELECT doc_id, source, text, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS pos
  FROM documents WHERE text IS NOT NULL),
n AS (SELECT *, trim(line, ' ' || chr(9) || chr(13)) AS norm FROM lines),
common AS (
  SELECT norm, min((doc_id IS NULL, doc_id, pos)) AS first FROM n WHERE length(norm) >= {MIN_CHARS}
  GROUP BY norm HAVING count(DISTINCT coalesce('s' || source, 'n')) >= {MIN_SITES}),
marked AS (
  SELECT n.*, c.norm IS NOT NULL AND (n.doc_id IS NULL, n.doc_id, n.pos) IS DISTINCT FROM c.first AS gone
  FROM n LEFT JOIN common c ON n.norm = c.norm),
kept AS (
  SELECT doc_id, text, count(*) AS n_lines, count(*) FILTER (gone) AS n_removed,
         coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '') AS rest
  FROM marked GROUP BY doc_id, text)
SELECT d.doc_id, coalesce(k.n_lines, 0)::BIGINT AS n_lines, coalesce(k.n_removed, 0)::BIGINT AS n_removed,
       coalesce(length(k.rest), 0)::BIGINT AS kept_chars, sha256(coalesce(k.rest, '')) AS kept_sha256
FROM documents d LEFT JOIN kept k ON d.doc_id IS NOT DISTINCT FROM k.doc_id AND d.text = k.text
"""
