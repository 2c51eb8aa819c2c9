"""What the text operators share: shared folders, row keys, joins that stand hot keys, connected components."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from trilist.plans.session import shared_folder

K1, K2 = "__ll_k1", "__ll_k2"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir, which all executors share; on a local master, where it may be unset, a temporary one."""
    return shared_folder(spark)


def scratch(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder, removed when the driver ends."""
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    atexit.register(remove, spark, path)
    return path


def remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    if spark.sparkContext._jsc is None or jvm is None:
        return
    try:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception as error:  # the session may be gone; the folder is then left to its owner
        print(f"trilist: {path} was not removed: {type(error).__name__}")


def materialise(df: DataFrame, tag: str, codec: str = "zstd") -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: cuts lineage and survives lost executors.

    codec: snappy for many small tables, whose writers then hold less memory outside the heap.
    """
    spark, path = df.sparkSession, scratch(df.sparkSession, tag)
    df.write.option("compression", codec).parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back._scratch_path = path
    return back


def discard(*tables: DataFrame) -> None:
    """Delete materialised tables that no later step reads."""
    for df in tables:
        if path := getattr(df, "_scratch_path", None):
            remove(df.sparkSession, path)


def release(spark: SparkSession) -> None:
    """Let Spark drop shuffle files of finished steps: its cleaner acts on what the driver's JVM has collected."""
    spark.sparkContext._jvm.System.gc()


def bounded_batches(spark: SparkSession, rows: int = 512) -> None:
    """Arrow batches of few rows, so that long texts do not pile up in one Python batch.

    Plans read the setting when they run, after the caller has them, so it stays; a smaller one of the user's is kept.
    """
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key, "10000"))
    if not 0 < now <= rows:
        spark.conf.set(key, str(rows))


def text_of(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def with_row_key(df: DataFrame, columns: Sequence[str] = ("doc_id", "text")) -> DataFrame:
    """Add a 128-bit key of the named columns, nulls included; equal rows have equal keys."""
    cols = [x for c in columns for x in (F.col(c), F.col(c).isNull())]
    return df.withColumn(K1, F.xxhash64(*cols)).withColumn(K2, F.xxhash64(F.lit("second"), *reversed(cols)))


def packed(docs: DataFrame, *columns: str) -> DataFrame:
    """Whole rows as a struct ``doc`` beside their row key and the named columns, so that no other column can clash."""
    rows = docs.select(F.struct(*(docs[c] for c in docs.columns)).alias("doc"))
    keyed = with_row_key(rows.select("doc", F.col("doc.doc_id"), F.col("doc.text")))
    return keyed.select("doc", K1, K2, *(F.col(f"doc.{c}") for c in columns))


def join_hot(left: DataFrame, right: DataFrame, keys: list[str], weight: str, total: int, share: float = 0.001, how: str = "inner") -> DataFrame:
    """Join left with right, one row per key in right; right[weight] counts the rows that left has of the key.

    At most 1/share keys have more than share of all rows, so these are broadcast (a proven bound) and their rows of
    left stay where they are; all other keys go through a shuffled join without skew. how: inner or left.
    """
    limit = max(1, int(total * share))
    hot = right.filter(F.col(weight) > limit)
    cold = right.filter(F.col(weight) <= limit)
    here = left.join(F.broadcast(hot), keys, "inner")
    rest = left.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(cold, keys, how)
    return here.unionByName(rest)


def join_dealt(left: DataFrame, right: DataFrame, key: str, total: int, counted: DataFrame | None = None, share: float = 0.001) -> DataFrame:
    """Join left with right, one wide row per key in right, each frequent key of left dealt over several tasks.

    A key with more than share of the rows goes in parts of that many rows, and its row of right is copied once a part,
    so right grows by at most 2/share rows; only the names and parts of these keys (at most 1/share) are broadcast.
    counted: a smaller table with the same keys as left, to count them on.
    """
    limit = max(1, int(total * share))
    hot = (left if counted is None else counted).groupBy(key).agg(F.count("*").alias("n")).filter(F.col("n") > limit)
    hot = F.broadcast(hot.select(key, F.ceil(F.col("n") / limit).cast("int").alias("parts")))
    parts = F.coalesce("parts", F.lit(1))
    others = [c for c in left.columns if c != key and dict(left.dtypes)[c] != "binary"]
    dealt = left.join(hot, key, "left").withColumn("part", F.pmod(F.xxhash64(*others), parts).cast("int")).drop("parts")
    copied = right.join(hot, key, "left").withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("parts")
    return dealt.join(copied, [key, "part"]).drop("part")


def components(edges: DataFrame, tag: str = "components", limit: int = 60) -> DataFrame:
    """Connected components of edges(a, b): rows (node, root) with root the smallest node of the component.

    Each round points every node at the smallest node it sees among its neighbours (large and small stars in turn),
    with tables in the shared folder between rounds; only two flags a round reach the driver.
    """
    pairs = materialise(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct(), tag, "snappy")
    for _ in range(limit):
        # settled: no node that others point at points anywhere itself, and none points twice
        inner = pairs.select(F.col("b").alias("a")).join(pairs, "a", "left_semi").select("a")
        if inner.isEmpty() and pairs.groupBy("a").count().filter("count > 1").isEmpty():
            break
        # large star: larger neighbours of a node go to the smallest node it sees
        both = pairs.union(pairs.select("b", "a"))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.join(least, "a").filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        # small star: a node and its smaller neighbours go to the smallest of these
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        joined = large.join(least, "a")
        small = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).union(joined.select("a", F.col("m").alias("b"))).filter("a <> b").distinct()
        last, pairs = pairs, materialise(small, tag, "snappy")
        discard(last)
    else:
        raise RuntimeError("components did not settle")
    found = pairs.select(F.col("a").alias("node"), F.col("b").alias("root"))
    found._scratch_path = pairs._scratch_path
    return found
