"""User-defined functions: Arrow and pandas kernels, a table function, nearest neighbours."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trilist.functions.params import Params


def parameter_rows(sizes: DataFrame) -> DataFrame:
    """A Python table function over a column of sizes: (n, name, value) by the finding rule."""

    @F.udtf(returnType="name string, value double")
    class Rules:
        def eval(self, n: int):
            p = Params.for_finding(n)
            yield "buckets", float(p.buckets)
            yield "sample_cap", float(p.sample_cap)

    spark = sizes.sparkSession
    spark.udtf.register("trilist_params", Rules)
    return spark.sql("SELECT n, name, value FROM {t}, LATERAL trilist_params(n)", t=sizes)


def finding_rules(sizes: DataFrame) -> DataFrame:
    """The parameters of the finding rule for each size n, by the Python class itself."""

    def run(batches):
        for pdf in batches:
            rules = [Params.for_finding(n) for n in pdf["n"].tolist()]
            yield pd.DataFrame([(p.n, round(p.eps, 9), round(p.threshold, 6), p.buckets, p.bucket_cap, p.sample_cap, round(p.r, 4)) for p in rules], columns=["n", "eps", "threshold", "buckets", "bucket_cap", "sample_cap", "r"])

    return sizes.mapInPandas(run, "n long, eps double, threshold double, buckets long, bucket_cap long, sample_cap long, r double")


def grouped_entropy(df: DataFrame, group: str, value: str) -> DataFrame:
    """(grp, entropy) by a grouped-aggregate pandas function over counts, so that no group travels row by row."""
    @F.pandas_udf("double")
    def entropy(counts: pd.Series) -> float:
        import numpy as np

        p = counts.to_numpy(dtype=float) / counts.sum()
        return float(-(p * np.log2(p)).sum()) + 0.0

    counts = df.groupBy(group, value).agg(F.count("*").alias("c"))
    return counts.groupBy(F.col(group).alias("grp")).agg(F.round(entropy("c"), 6).alias("entropy"))


def triangles_per_cell(customers: DataFrame) -> DataFrame:
    """(cell, triangles): a grouped map over nations, each a clique of its customers."""

    def kernel(pdf):
        n = len(pdf)
        return pd.DataFrame({"cell": [pdf["cell"].iloc[0]], "triangles": [n * (n - 1) * (n - 2) // 6]})

    return customers.select(F.col("c_nationkey").alias("cell"), "c_custkey").groupBy("cell").applyInPandas(kernel, "cell int, triangles long")


def hash61(x, c0, c1, c2, buckets: int):
    """The 61-bit polynomial hash for pandas columns of ids beyond 31 bits."""
    from trilist.functions.coins import PRIME61

    return [((int(c) * int(v) + int(b)) % PRIME61 * int(v) + int(a)) % PRIME61 % buckets for v, a, b, c in zip(x, c0, c1, c2)]


def knn_edges(vectors: DataFrame, k: int, block: int = 4096) -> DataFrame:
    """Edges (u, v) between each vector and its k nearest by cosine, in blocks of bounded size against all rows.

    Rows fall into blocks by a hash; each pair of blocks is one grouped kernel, and the k best of each row are merged.
    """
    n = vectors.count()
    blocks = max(1, -(-n // block))
    rows = vectors.select("vec_id", "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("b"))
    left = rows.withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select("vec_id", "embedding", F.col("b").alias("i"), F.col("o").alias("j"))
    right = rows.withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select("vec_id", "embedding", F.col("o").alias("i"), F.col("b").alias("j"))

    def best(x, y):
        import numpy as np
        if x.empty or y.empty:
            return pd.DataFrame({"u": [], "v": [], "s": []}).astype({"u": "int64", "v": "int64", "s": "float64"})
        p, q = (np.stack(f["embedding"].to_numpy()).astype(float) for f in (x, y))
        s = (p / np.linalg.norm(p, axis=1, keepdims=True)) @ (q / np.linalg.norm(q, axis=1, keepdims=True)).T
        s[x["vec_id"].to_numpy()[:, None] == y["vec_id"].to_numpy()[None]] = -2
        top = np.argsort(-s, axis=1, kind="stable")[:, :k]
        return pd.DataFrame({"u": np.repeat(x["vec_id"].to_numpy(), top.shape[1]), "v": y["vec_id"].to_numpy()[top.ravel()], "s": np.take_along_axis(s, top, 1).ravel()})

    from pyspark.sql import Window

    near = left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInPandas(best, "u long, v long, s double").filter("s > -2")
    kept = near.withColumn("r", F.row_number().over(Window.partitionBy("u").orderBy(F.desc("s"), "v"))).filter(F.col("r") <= k)
    return kept.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()
