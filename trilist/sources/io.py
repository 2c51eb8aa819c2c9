"""Edge lists in files, bucketed tables and SQL views."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from trilist.plans.session import shared_folder
from trilist.sources.graphs import EDGES, arcs, require_schema


def scratch_path(spark: SparkSession) -> str:
    """A new path in the shared folder."""
    return f"{shared_folder(spark)}/trilist-{uuid.uuid4().hex}"


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", files: int | None = None) -> None:
    """Edges clustered and sorted by u, so that later reads by u prune row groups."""
    out = edges.repartition(files, "u") if files else edges
    out.sortWithinPartitions("u", "v").write.format(fmt).mode("overwrite").save(path)


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    return require_schema(spark.read.schema(EDGES).format(fmt).load(path), EDGES)


def round_trip(edges: DataFrame, fmt: str) -> DataFrame:
    path = scratch_path(edges.sparkSession)
    write_edges(edges, path, fmt, 4)
    return read_edges(edges.sparkSession, path, fmt)


def save_arcs(edges: DataFrame, table: str, buckets: int) -> None:
    """Arcs bucketed by src: wedge joins on src then need no exchange."""
    arcs(edges).write.bucketBy(buckets, "src").sortBy("src", "dst").mode("overwrite").saveAsTable(table)


def register(edges: DataFrame, prefix: str = "") -> None:
    """Temp views edges, arcs and vertices."""
    edges.createOrReplaceTempView(f"{prefix}edges")
    arcs(edges).createOrReplaceTempView(f"{prefix}arcs")
    arcs(edges).selectExpr("src AS v").distinct().createOrReplaceTempView(f"{prefix}vertices")
