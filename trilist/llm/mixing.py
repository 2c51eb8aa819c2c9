"""Mixing sources to target weights, with DataFrame functions only.

Every row gets a hash-random key. Within a source, rows are put in ranges of that key (about ``rows_per_range`` rows each),
the ranges' sizes are summed and prefixed, and inside each range a running sum places every row exactly. A source's
budget is then cut at one point of that order: rows before it are taken once more than rows after it, the row that holds
the cut is taken in part, and a budget above the source's size repeats whole epochs first.

Edge cases: null text has size 0 and takes nothing; a null source is a source of its own, after all others; equal rows
(same doc_id and text) are interchangeable; a source of size 0 has target 0; an empty table gives no rows; other columns
are ignored by the plan and kept by ``mix_documents``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trilist.llm.common import join_hot, materialise, packed, read_table, text_of

#: Words of the contract: runs of bytes other than space, tab, line feed, vertical tab, form feed, carriage return.
WORD = r"[^\x20\x09-\x0D]+"


def named() -> Column:
    """The source as a key without nulls."""
    return F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("n"))


def mix_key(seed: int) -> Column:
    """A key that is random to the eye and the same in each run: 32 hex digits from doc_id and text."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit("~")), F.md5(text_of())))


def targets(sizes: DataFrame, weights: tuple[int, ...], share: float, max_epochs: float) -> DataFrame:
    """Per source: share of all sizes by weight, capped at max_epochs times its size, the excess dealt again by weight.

    The shared level is found in closed form: with sources in order of cap / weight, the level after k capped sources is
    (budget - their caps) / (weights of the others); the first source that stays under its cap fixes it. One row per
    source goes through a single task here.
    """
    by_name = Window.orderBy("name_null", "source")
    ranked = (
        sizes.withColumn("name_null", F.col("source").isNull().cast("int"))
        .withColumn("place", F.row_number().over(by_name))
        .withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), ((F.col("place") - 1) % len(weights) + 1).cast("int")))
        .withColumn("cap", F.lit(float(max_epochs)) * F.col("source_size"))
        .withColumn("ratio", F.col("cap") / F.col("weight"))
        .withColumn("budget", F.lit(float(share)) * F.sum("source_size").over(Window.partitionBy()))
    )
    order = Window.orderBy("ratio", "place")
    levels = (
        ranked.withColumn("at", F.row_number().over(order))
        .withColumn("capped", F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("others", F.sum("weight").over(order.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("level", (F.col("budget") - F.col("capped")) / F.col("others"))
    )
    fixed = F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("at", "level"))).over(Window.partitionBy())
    found = levels.withColumn("fixed", fixed)
    target = F.when(F.col("fixed").isNull() | (F.col("at") < F.col("fixed.at")), F.col("cap")).otherwise(F.col("fixed.level") * F.col("weight"))
    return found.select("name", "source_size", "source_rows", F.round(F.least(target, F.col("cap")), 6).alias("target"))


def prefixed(sums: DataFrame, fan: int = 4096) -> DataFrame:
    """For sums(name, range, range_size): offset, the size of all earlier ranges of the source, in two levels.

    Ranges meet in blocks of fan, and then the blocks: with 1e9 ranges no task has more than 250,000 rows of a source.
    """
    block = F.floor(F.col("range") / F.lit(fan)).cast("long")
    earlier = lambda *by: Window.partitionBy(*by).rowsBetween(Window.unboundedPreceding, -1)
    inside = sums.withColumn("block", block).withColumn("within", F.coalesce(F.sum("range_size").over(earlier("name", "block").orderBy("range")), F.lit(0)))
    blocks = sums.groupBy("name", block.alias("block")).agg(F.sum("range_size").alias("block_size"))
    blocks = blocks.withColumn("ahead", F.coalesce(F.sum("block_size").over(earlier("name").orderBy("block")), F.lit(0))).drop("block_size")
    return inside.join(blocks, ["name", "block"]).select("name", "range", "range_size", (F.col("within") + F.col("ahead")).alias("offset"))


def plan_mix(docs: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, max_epochs: float = 2.0, seed: int = 8, rows_per_range: int = 1024) -> DataFrame:
    """Rows (mix_key, doc_id, name, size, source_size, target, taken), one for each row of docs."""
    size = F.regexp_count(text_of(), F.lit(WORD)).cast("long")
    sized = materialise(docs.select("doc_id", "source", named().alias("name"), size.alias("size"), mix_key(seed).alias("mix_key")), "mix-sizes")
    totals = targets(sized.groupBy("name", "source").agg(F.sum("size").alias("source_size"), F.count("*").alias("source_rows")), weights, share, max_epochs)
    # the key's first 15 hex digits, below 2^60, pick the range; equal widths, as keys are uniform
    lead = F.conv(F.substring("mix_key", 1, 15), 16, 10).cast("long")
    ranges = F.greatest(F.lit(1.0), F.ceil(F.col("source_rows") / F.lit(rows_per_range)).cast("double"))
    placed = join_hot(sized, totals.select("name", "source_rows"), ["name"], "source_rows", sized.count())
    placed = placed.withColumn("range", F.least(F.floor(lead / F.lit(float(2**60)) * ranges), ranges.cast("long") - 1))
    sums = prefixed(placed.groupBy("name", "range").agg(F.sum("size").alias("range_size")))
    whole = F.floor("target")
    cuts = (
        sums.join(totals, "name")
        .withColumn("epochs", F.when(F.col("source_size") > 0, F.floor(whole / F.col("source_size"))).otherwise(F.lit(0)))
        .withColumn("rest", whole - F.col("epochs") * F.col("source_size"))
        .select("name", "range", "offset", "epochs", "rest", "source_size", "target")
    )
    inside = Window.partitionBy("name", "range").orderBy("mix_key").rowsBetween(Window.unboundedPreceding, -1)
    run = F.coalesce(F.sum("size").over(inside), F.lit(0))
    rows = placed.withColumn("inside", run).join(cuts, ["name", "range"])
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("rest") - F.col("offset") - F.col("inside")))
    return rows.select("mix_key", "doc_id", "name", "size", "source_size", "target", (F.col("epochs") * F.col("size") + part).cast("long").alias("taken"))


def mix_documents(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: the columns of docs, then size, taken and copies (passes over the text, the last one maybe in part).

    Rows of which nothing is taken are left out. Repeated rows share a key, and the words taken of them are dealt evenly.
    Columns of docs that are named like the three new ones are left out for them.
    """
    seed = options.get("seed", 8)
    per_key = plan_mix(docs, **options).groupBy("mix_key").agg(F.sum("taken").alias("all_taken"), F.count("*").alias("rows"), F.first("size").alias("mix_size"))
    rows = packed(docs, "doc_id", "text").select("doc", mix_key(seed).alias("mix_key"))
    kept = join_hot(rows, per_key.filter("all_taken > 0"), ["mix_key"], "rows", max(1, docs.count()))
    taken = F.col("all_taken") / F.col("rows")
    own = [F.col(f"doc.`{c}`").alias(c) for c in docs.columns if c not in ("mix_size", "mix_taken", "mix_copies")]
    return kept.select(*own, "mix_size", F.ceil(taken).cast("long").alias("mix_taken"), F.ceil(taken / F.col("mix_size")).cast("long").alias("mix_copies"))


def op8_source_mix(spark, sf_dir: str) -> DataFrame:
    """Weights 3, 1, 2 by source, 150 % of all words, at most two passes over a source."""
    return plan_mix(read_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


OP8_SQL = r"""
WITH sized AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         md5(concat_ws(':', '8', coalesce(doc_id::VARCHAR, '~'), md5(coalesce(text, '')))) AS k
  FROM documents),
src AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
r1 AS (SELECT *, row_number() OVER (ORDER BY (source IS NULL)::INT, source) AS place,
              1.5::DOUBLE * sum(source_size) OVER () AS budget FROM src),
r2 AS (SELECT *, CASE (place - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS weight, 2.0::DOUBLE * source_size AS cap FROM r1),
r3 AS (SELECT *, cap / weight AS ratio, row_number() OVER (ORDER BY cap / weight, place) AS ord FROM r2),
r4 AS (SELECT *, (budget - coalesce(sum(cap) OVER (ORDER BY ord ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0))
              / sum(weight) OVER (ORDER BY ord ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM r3),
r5 AS (SELECT min(ord) AS ord0 FROM r4 WHERE level <= ratio),
tg AS (SELECT r4.source, r4.source_size,
              round(least(cap, CASE WHEN ord0 IS NULL OR ord < ord0 THEN cap ELSE (SELECT level FROM r4, r5 WHERE ord = ord0) * weight END), 6) AS target
       FROM r4, r5),
run AS (SELECT s.doc_id, s.size, t.source_size, t.target,
               coalesce(sum(s.size) OVER (PARTITION BY s.source ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before
        FROM sized s JOIN tg t ON s.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target::DOUBLE AS target,
       (CASE WHEN source_size > 0 THEN (floor(target)::BIGINT // source_size) * size
             + greatest(0, least(size, floor(target)::BIGINT % source_size - before)) ELSE 0 END)::BIGINT AS taken
FROM run
"""
