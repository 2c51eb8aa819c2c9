"""Graphs as edge tables (u, v) with u < v, built from the given tables; and the same in SQL.

Builders drop null end points, self loops and repeated edges, so every graph is simple. Ids are the tables' own keys;
typed graphs interleave (key * types + type).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from trilist.functions.coins import pair_hits, sql_coin
from trilist.plans.session import cut

EDGES = T.StructType([T.StructField("u", T.LongType()), T.StructField("v", T.LongType())])
MIN_LINE = 20


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def require_schema(df: DataFrame, schema: T.StructType) -> DataFrame:
    want, have = [(f.name, f.dataType) for f in schema], [(f.name, f.dataType) for f in df.schema]
    if want != have:
        raise ValueError(f"columns {have}, not {want}")
    return df


def normalise_edges(df: DataFrame, a: str = "u", b: str = "v") -> DataFrame:
    pair = df.select(F.least(a, b).cast("long").alias("u"), F.greatest(a, b).cast("long").alias("v"), F.col(a).alias("_a"), F.col(b).alias("_b"))
    return pair.filter("_a IS NOT NULL AND _b IS NOT NULL AND u < v").select("u", "v").distinct()


def edges_from_columns(df: DataFrame, a: Column, b: Column) -> DataFrame:
    return normalise_edges(df.select(a.alias("u"), b.alias("v")))


def edges_from_groups(df: DataFrame, member: Column, group: list[Column], max_group: int | None = None, min_group: int = 2) -> DataFrame:
    """An edge between any two members of a group; groups beyond max_group members (a limit of the graph's definition) have none."""
    names = [f"g{i}" for i in range(len(group))]
    rows = df.select(member.cast("long").alias("m"), *(g.alias(n) for g, n in zip(group, names))).dropna().distinct()
    if max_group is not None:
        sizes = rows.groupBy(*names).agg(F.count("*").alias("c")).filter(F.col("c").between(min_group, max_group))
        rows = rows.join(sizes.select(*names), names)
    return rows.withColumnRenamed("m", "u").join(rows.withColumnRenamed("m", "v"), names).filter("u < v").select("u", "v").distinct()


def arcs(edges: DataFrame) -> DataFrame:
    """Each edge in both directions."""
    return edges.select(F.explode(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))).alias("x")).select("x.src", "x.dst")


def from_sql(sql: str, *tables: str) -> Callable[[SparkSession, str], DataFrame]:
    """A builder from SQL that both engines read alike; the tables are passed as frames, not registered."""

    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(sql, **{t: load(spark, sf_dir, t) for t in tables})

    return build


@dataclass(frozen=True)
class Graph:
    """build gives EDGES; sql the same for DuckDB; n counts all vertices, isolated ones included, from the key table."""

    build: Callable[[SparkSession, str], DataFrame]
    sql: str
    vertices: str = ""  # SQL that gives all vertices v


def id_blocks(ids: DataFrame, block: int) -> DataFrame:
    """(b, vs): the ids v in blocks of about so many, the blocks one after another in the order of the ids."""
    ranged = ids.repartitionByRange(max(1, -(-ids.count() // block)), "v")
    return cut(ranged.groupBy(F.spark_partition_id().alias("b")).agg(F.array_sort(F.collect_list("v")).alias("vs")))


def coin_pairs(ids: DataFrame, seed: int, block: int = 512) -> DataFrame:
    """(u, v), u < v: pairs of ids v whose coin shows head; the coins of two blocks are thrown together, and only pairs that fall leave the task."""
    b = id_blocks(ids, block)
    met = b.select(F.col("b").alias("i"), F.col("vs").alias("x")).join(b.select(F.col("b").alias("j"), F.col("vs").alias("y")), F.col("i") <= F.col("j"))
    # the table may be one small file, so the tiles are dealt over the tasks
    tiles = met.repartition(8 * ids.sparkSession.sparkContext.defaultParallelism, "i", "j").select("x", "y")

    def throw(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            for x, y in zip(batch.column("x"), batch.column("y")):
                x, y = x.values.to_numpy(), y.values.to_numpy()
                i, j = np.nonzero(pair_hits(seed, x, y) & (x[:, None] < y))
                yield pa.RecordBatch.from_arrays([pa.array(x[i]), pa.array(y[j])], names=["u", "v"])

    return tiles.mapInArrow(throw, EDGES)


def _coin_half(spark, sf_dir):
    """A coin for each pair of suppliers."""
    return coin_pairs(load(spark, sf_dir, "supplier").select(F.col("s_suppkey").cast("long").alias("v")).dropna(), 7)


def _cohour(spark, sf_dir):
    return edges_from_groups(load(spark, sf_dir, "events"), F.col("user_id"), [F.date_trunc("hour", "ts"), F.col("event_type")])


def _part_supplier(spark, sf_dir):
    return edges_from_columns(load(spark, sf_dir, "lineitem"), F.col("l_partkey") * 2, F.col("l_suppkey") * 2 + 1)


def _forest(spark, sf_dir):
    region = load(spark, sf_dir, "nation").select((F.col("n_nationkey") * 3 + 1).alias("a"), (F.col("n_regionkey") * 3).alias("b"))
    nation = load(spark, sf_dir, "customer").select((F.col("c_custkey") * 3 + 2).alias("a"), (F.col("c_nationkey") * 3 + 1).alias("b"))
    return normalise_edges(region.union(nation), "a", "b")


def _customer_cycle(spark, sf_dir):
    """Each customer's key and the next number, the last key and the first."""
    c = load(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("k"))
    ends = F.broadcast(c.agg(F.min("k").alias("first"), F.max("k").alias("last")))
    return edges_from_columns(c.join(ends), F.col("k"), F.when(F.col("k") < F.col("last"), F.col("k") + 1).otherwise(F.col("first")))


def _quantities(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").select(F.col("l_quantity").cast("long").alias("q")).dropna().distinct()


def _quantity_complete(spark, sf_dir):
    q = _quantities(spark, sf_dir)
    return q.withColumnRenamed("q", "u").join(q.withColumnRenamed("q", "v"), F.col("u") < F.col("v"))


def _quantity_cycle(spark, sf_dir):
    """Each quantity and the next larger one, the largest and the smallest; there are few, so one window over all."""
    every = Window.partitionBy(F.lit(0))
    return edges_from_columns(_quantities(spark, sf_dir).select("q", F.coalesce(F.lead("q").over(every.orderBy("q")), F.min("q").over(every)).alias("next")), F.col("q"), F.col("next"))


def _part_loops(spark, sf_dir):
    """Only self loops, which no graph keeps."""
    return edges_from_columns(load(spark, sf_dir, "lineitem"), F.col("l_partkey"), F.col("l_partkey"))


def _far_parts(spark, sf_dir):
    return edges_from_columns(load(spark, sf_dir, "lineitem").agg(F.min("l_partkey").alias("a"), F.max("l_partkey").alias("b")), F.col("a"), F.col("b"))


def _cells(spark, sf_dir):
    return edges_from_groups(load(spark, sf_dir, "customer"), F.col("c_custkey"), [F.col("c_nationkey"), F.col("c_mktsegment")])


def cell_members(spark, sf_dir):
    """(m, g0, g1): the groups behind the graph of the cells."""
    return load(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("m"), F.col("c_nationkey").alias("g0"), F.col("c_mktsegment").alias("g1"))


def _supplier_nation(spark, sf_dir):
    return edges_from_groups(load(spark, sf_dir, "supplier"), F.col("s_suppkey"), [F.col("s_nationkey")])


def _book(spark, sf_dir):
    s = load(spark, sf_dir, "supplier")
    return normalise_edges(s.select(F.explode(F.array(F.lit(0), F.lit(1))).alias("a"), F.col("s_suppkey").alias("b")), "a", "b")


def _windmill(spark, sf_dir):
    s = load(spark, sf_dir, "supplier").filter("s_suppkey > 0")
    last = s.agg(F.max("s_suppkey").alias("m"))
    hub = s.select(F.lit(0).alias("a"), F.col("s_suppkey").alias("b"))
    blades = s.filter("s_suppkey % 2 = 1").join(F.broadcast(last), F.col("s_suppkey") < F.col("m")).select(F.col("s_suppkey").alias("a"), (F.col("s_suppkey") + 1).alias("b"))
    return normalise_edges(hub.union(blades), "a", "b")


def _halfyear(spark, sf_dir):
    l = load(spark, sf_dir, "lineitem").filter("l_shipdate >= '1998-01-01' AND l_shipdate < '1998-07-01'")
    return edges_from_groups(l, F.col("l_suppkey"), [F.col("l_orderkey")])


def _copurchase(spark, sf_dir):
    return edges_from_groups(load(spark, sf_dir, "lineitem"), F.col("l_partkey"), [F.col("l_orderkey")])


def _trade(spark, sf_dir):
    lo = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    c, p, s = F.col("o_custkey") * 3, F.col("l_partkey") * 3 + 1, F.col("l_suppkey") * 3 + 2
    return normalise_edges(lo.select(F.explode(F.array(*(F.struct(x.alias("a"), y.alias("b")) for x, y in ((c, p), (c, s), (p, s))))).alias("e")).select("e.a", "e.b"), "a", "b")


def _document_lines(spark, sf_dir):
    """By definition only lines of 2 to 50 documents make edges: a line of more is boilerplate and says nothing of two documents."""
    lines = load(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("l")).withColumn("l", F.trim("l")).filter(F.length("l") >= MIN_LINE)
    return edges_from_groups(lines, F.col("doc_id"), [F.col("l")], max_group=50)


def _labels(spark, sf_dir):
    return edges_from_groups(load(spark, sf_dir, "embeddings"), F.col("vec_id"), [F.col("label")])


def _hosts(spark, sf_dir):
    return edges_from_groups(load(spark, sf_dir, "pages"), F.col("page_id"), [F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1)])


def _links(spark, sf_dir):
    """By definition only targets of 2 to 20 pages make edges: more common ones (navigation) say nothing of two pages."""
    refs = load(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("h"))
    return edges_from_groups(refs, F.col("page_id"), [F.col("h")], max_group=20)


def word_windows(texts: DataFrame, key: str, width: int = 10) -> DataFrame:
    """(key, h1, h2), distinct: 128-bit hashes of all runs of width words of the column text, whole texts."""
    words = F.filter(F.split("text", r"[ \t\n\r\x0B\f]+"), lambda w: w != "")
    spans = F.when(F.size("w") >= width, F.sequence(F.lit(1), F.size("w") - (width - 1)))
    hashes = F.transform(spans, lambda i: F.struct(F.xxhash64(F.slice("w", i, width)).alias("h1"), F.xxhash64(F.lit("second"), F.slice("w", i, width)).alias("h2")))
    return texts.select(key, words.alias("w")).select(key, F.explode(hashes).alias("h")).select(key, "h.h1", "h.h2").distinct()


def _overlap(spark, sf_dir):
    """A document and a benchmark item that share ten words in a row, by an equi-join of window hashes; shorter items have no edge."""
    d, b = word_windows(load(spark, sf_dir, "documents"), "doc_id"), word_windows(load(spark, sf_dir, "benchmark"), "item_id")
    return normalise_edges(d.join(b, ["h1", "h2"]).select((F.col("doc_id") * 2).alias("a"), (F.col("item_id") * 2 + 1).alias("b")).distinct(), "a", "b")


def _turns(spark, sf_dir):
    return edges_from_groups(load(spark, sf_dir, "conversations"), F.col("conv_id") * 1000 + F.col("turn"), [F.col("conv_id")])


def _quality_lines(spark, sf_dir):
    keep = load(spark, sf_dir, "labels").filter("quality = 1").select("doc_id")
    return induced(_document_lines(spark, sf_dir), keep.select(F.col("doc_id").alias("v")))


def induced(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among vertices(v)."""
    return edges.join(vertices.select(F.col("v").alias("u")), "u", "left_semi").join(vertices.select("v"), "v", "left_semi").select("u", "v")


def small(edges: list[tuple[int, int]]) -> Graph:
    rows = ", ".join(f"({a}::BIGINT, {b}::BIGINT)" for a, b in edges)
    sql = f"SELECT * FROM (VALUES {rows}) t(u, v)" if edges else "SELECT 0::BIGINT AS u, 0::BIGINT AS v WHERE false"
    return Graph(lambda spark, _: spark.createDataFrame(edges, EDGES), sql)


def pair_sql(member: str, group: str, table: str, extra: str = "") -> str:
    return f"SELECT DISTINCT x.m AS u, y.m AS v FROM (SELECT DISTINCT ({member})::BIGINT AS m, {group} AS g FROM {table} {extra}) x JOIN (SELECT DISTINCT ({member})::BIGINT AS m, {group} AS g FROM {table} {extra}) y ON x.g = y.g AND x.m < y.m"


def norm_sql(rows: str) -> str:
    return f"SELECT DISTINCT least(a, b)::BIGINT AS u, greatest(a, b)::BIGINT AS v FROM ({rows}) WHERE a <> b"


def capped_sql(rows: str, most: int) -> str:
    return f"SELECT DISTINCT x.m AS u, y.m AS v FROM ({rows}) x JOIN ({rows}) y ON x.g = y.g AND x.m < y.m JOIN (SELECT g FROM ({rows}) GROUP BY g HAVING count(*) BETWEEN 2 AND {most}) z ON z.g = x.g"


def window_sql(table: str, key: str) -> str:
    words = f"SELECT {key}, list_filter(string_split_regex(text, '[ \\t\\n\\r\\x0B\\f]+'), lambda x: x <> '') AS w FROM {table} WHERE text IS NOT NULL"
    return f"SELECT DISTINCT {key}, array_to_string(list_slice(w, i, i + 9), ' ') AS k FROM (SELECT {key}, w, unnest(range(1, len(w) - 8)) AS i FROM ({words}) WHERE len(w) >= 10)"


LINES_SQL = f"SELECT DISTINCT doc_id AS m, l AS g FROM (SELECT doc_id, trim(unnest(string_split(text, chr(10)))) AS l FROM documents) WHERE length(l) >= {MIN_LINE}"
HREF_SQL = """SELECT DISTINCT page_id AS m, h AS g FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS h FROM pages)"""
QUANTITIES = "SELECT DISTINCT l_quantity::BIGINT AS q FROM lineitem WHERE l_quantity IS NOT NULL"
SUPPLIERS = "SELECT s_suppkey AS v FROM supplier"
GRAPHS: dict[str, Graph] = {
    "coin": Graph(_coin_half, f"SELECT x.s_suppkey AS u, y.s_suppkey AS v FROM supplier x JOIN supplier y ON x.s_suppkey < y.s_suppkey WHERE {sql_coin(7, 'x.s_suppkey', 'y.s_suppkey')} < {2**31}", SUPPLIERS),
    "cohour": Graph(_cohour, pair_sql("user_id", "(date_trunc('hour', ts), event_type)", "events"), "SELECT DISTINCT user_id AS v FROM events"),
    "part_supplier": Graph(_part_supplier, norm_sql("SELECT l_partkey * 2 AS a, l_suppkey * 2 + 1 AS b FROM lineitem"), "SELECT p_partkey * 2 AS v FROM part UNION ALL SELECT s_suppkey * 2 + 1 FROM supplier"),
    "forest": Graph(_forest, norm_sql("SELECT n_nationkey * 3 + 1 AS a, n_regionkey * 3 AS b FROM nation UNION ALL SELECT c_custkey * 3 + 2, c_nationkey * 3 + 1 FROM customer"), "SELECT r_regionkey * 3 AS v FROM region UNION ALL SELECT n_nationkey * 3 + 1 FROM nation UNION ALL SELECT c_custkey * 3 + 2 FROM customer"),
    "cells": Graph(_cells, pair_sql("c_custkey", "(c_nationkey, c_mktsegment)", "customer"), "SELECT c_custkey AS v FROM customer"),
    "supplier_nation": Graph(_supplier_nation, pair_sql("s_suppkey", "s_nationkey", "supplier"), SUPPLIERS),
    "book": Graph(_book, norm_sql("SELECT h AS a, s_suppkey AS b FROM supplier, (VALUES (0), (1)) t(h)"), SUPPLIERS),
    "windmill": Graph(_windmill, norm_sql("SELECT 0 AS a, s_suppkey AS b FROM supplier UNION ALL SELECT s_suppkey, s_suppkey + 1 FROM supplier WHERE s_suppkey % 2 = 1 AND s_suppkey < (SELECT max(s_suppkey) FROM supplier)"), SUPPLIERS),
    "halfyear": Graph(_halfyear, pair_sql("l_suppkey", "l_orderkey", "lineitem", "WHERE l_shipdate >= '1998-01-01' AND l_shipdate < '1998-07-01'"), SUPPLIERS),
    "copurchase": Graph(_copurchase, pair_sql("l_partkey", "l_orderkey", "lineitem"), "SELECT p_partkey AS v FROM part"),
    "trade": Graph(_trade, norm_sql("SELECT unnest([o_custkey * 3, o_custkey * 3, l_partkey * 3 + 1]) AS a, unnest([l_partkey * 3 + 1, l_suppkey * 3 + 2, l_suppkey * 3 + 2]) AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey"), "SELECT c_custkey * 3 AS v FROM customer UNION ALL SELECT p_partkey * 3 + 1 FROM part UNION ALL SELECT s_suppkey * 3 + 2 FROM supplier"),
    "document_lines": Graph(_document_lines, capped_sql(LINES_SQL, 50), "SELECT DISTINCT doc_id AS v FROM documents"),
    "labels": Graph(_labels, pair_sql("vec_id", "label", "embeddings"), "SELECT vec_id AS v FROM embeddings"),
    "hosts": Graph(_hosts, pair_sql("page_id", "regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)", "pages"), "SELECT page_id AS v FROM pages"),
    "links": Graph(_links, capped_sql(HREF_SQL, 20), "SELECT page_id AS v FROM pages"),
    "overlap": Graph(_overlap, norm_sql(f"SELECT DISTINCT doc_id * 2 AS a, item_id * 2 + 1 AS b FROM ({window_sql('documents', 'doc_id')}) d JOIN ({window_sql('benchmark', 'item_id')}) b USING (k)"), "SELECT doc_id * 2 AS v FROM documents UNION ALL SELECT item_id * 2 + 1 FROM benchmark"),
    "turns": Graph(_turns, pair_sql("conv_id * 1000 + turn", "conv_id", "conversations"), "SELECT conv_id * 1000 + turn AS v FROM conversations"),
    "quality_lines": Graph(_quality_lines, f"SELECT u, v FROM ({capped_sql(LINES_SQL, 50)}) WHERE u IN (SELECT doc_id FROM labels WHERE quality = 1) AND v IN (SELECT doc_id FROM labels WHERE quality = 1)", "SELECT doc_id AS v FROM labels WHERE quality = 1"),
    "customer_cycle": Graph(_customer_cycle, norm_sql("SELECT c_custkey AS a, CASE WHEN c_custkey < (SELECT max(c_custkey) FROM customer) THEN c_custkey + 1 ELSE (SELECT min(c_custkey) FROM customer) END AS b FROM customer")),
    "quantity_complete": Graph(_quantity_complete, f"SELECT x.q AS u, y.q AS v FROM ({QUANTITIES}) x JOIN ({QUANTITIES}) y ON x.q < y.q"),
    "quantity_cycle": Graph(_quantity_cycle, norm_sql(f"SELECT q AS a, coalesce(lead(q) OVER (ORDER BY q), min(q) OVER ()) AS b FROM ({QUANTITIES})")),
    "part_loops": Graph(_part_loops, norm_sql("SELECT l_partkey AS a, l_partkey AS b FROM lineitem")),
    "far_parts": Graph(_far_parts, norm_sql("SELECT min(l_partkey) AS a, max(l_partkey) AS b FROM lineitem")),
    "empty": small([]),
    "one_edge": small([(0, 1)]),
    "triangle": small([(0, 1), (0, 2), (1, 2)]),
    "path": small([(i, i + 1) for i in range(5)]),
    "cycle": small([(i, i + 1) for i in range(7)] + [(0, 7)]),
    "star": small([(0, i) for i in range(1, 9)]),
    "complete": small([(i, j) for i in range(8) for j in range(i + 1, 8)]),
}


def edges_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return require_schema(GRAPHS[name].build(spark, sf_dir).select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")), EDGES)


#: Builders of the vertex tables, isolated vertices included.
def vertices_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    from_tables = {
        "coin": ("supplier", "s_suppkey", 1, 0), "book": ("supplier", "s_suppkey", 1, 0), "windmill": ("supplier", "s_suppkey", 1, 0), "halfyear": ("supplier", "s_suppkey", 1, 0),
        "supplier_nation": ("supplier", "s_suppkey", 1, 0), "cells": ("customer", "c_custkey", 1, 0), "copurchase": ("part", "p_partkey", 1, 0), "cohour": ("events", "user_id", 1, 0),
        "document_lines": ("documents", "doc_id", 1, 0), "labels": ("embeddings", "vec_id", 1, 0), "hosts": ("pages", "page_id", 1, 0), "links": ("pages", "page_id", 1, 0),
    }
    typed = {
        "part_supplier": [("part", "p_partkey", 2, 0), ("supplier", "s_suppkey", 2, 1)],
        "forest": [("region", "r_regionkey", 3, 0), ("nation", "n_nationkey", 3, 1), ("customer", "c_custkey", 3, 2)],
        "trade": [("customer", "c_custkey", 3, 0), ("part", "p_partkey", 3, 1), ("supplier", "s_suppkey", 3, 2)],
        "overlap": [("documents", "doc_id", 2, 0), ("benchmark", "item_id", 2, 1)],
    }
    if name == "turns":
        return load(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("v")).distinct()
    if name == "quality_lines":
        return load(spark, sf_dir, "labels").filter("quality = 1").select(F.col("doc_id").alias("v")).distinct()
    if name in from_tables or name in typed:
        parts = [load(spark, sf_dir, t).select((F.col(c) * k + o).cast("long").alias("v")) for t, c, k, o in typed.get(name) or [from_tables[name]]]
        out = parts[0]
        for p in parts[1:]:
            out = out.union(p)
        return out.distinct()
    return edges_of(spark, sf_dir, name).select(F.explode(F.array("u", "v")).alias("v")).distinct()


def vertices_sql(name: str) -> str:
    g = GRAPHS[name]
    return f"SELECT DISTINCT v::BIGINT AS v FROM ({g.vertices})" if g.vertices else f"SELECT DISTINCT unnest([u, v]) AS v FROM ({g.sql})"
