"""Unstructured graphs on the given tables, as (vertices (id), edges (src, dst)); ids of bipartite graphs are disjoint."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fieldseg.sources.fields import cents, table

Graph = tuple[DataFrame, DataFrame]


def turn_chain(spark: SparkSession, sf_dir: str) -> Graph:
    """Turns of conversations, each tied to the next; id = 16 * conversation + turn."""
    t = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 16 + F.col("turn")).alias("id")).distinct()
    nxt = t.select((F.col("id") - 1).alias("src"), F.col("id").alias("dst")).where("dst % 16 > 0")
    return t, nxt.join(t.select(F.col("id").alias("src")), "src", "left_semi").select("src", "dst")


def order_part(spark: SparkSession, sf_dir: str, predicate: str = "discount = 10 and quantity >= 45") -> Graph:
    """Orders (2 * key) and parts (2 * key + 1) of the lines that meet a predicate over `discount` (hundredths) and `quantity`."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", cents("l_discount").alias("discount"), F.col("l_quantity").cast("long").alias("quantity"))
    e = line.where(predicate).select((F.col("l_orderkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst")).distinct()
    return _ends(e), e


def _ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("id")).union(edges.select(F.col("dst").alias("id"))).distinct()


def _stars(members: DataFrame, key: str) -> DataFrame:
    """Edges from the least member of a key to the others: one less than members, where all pairs would be a square.

    The least is a map-side minimum, so a hot key costs no task that sorts its members; a null key ties nothing.
    """
    known = members.where(F.col(key).isNotNull())
    least = known.groupBy(key).agg(F.min("id").alias("src"), F.max("id").alias("_fs_last")).where(F.col("src") < F.col("_fs_last")).drop("_fs_last")
    return known.join(least, key).select("src", F.col("id").alias("dst")).where("src <> dst").distinct()


def doc_shared_lines(spark: SparkSession, sf_dir: str, longer_than: int = 40) -> Graph:
    """Documents that share a long line."""
    docs = table(spark, sf_dir, "documents")
    lines = docs.select(F.col("doc_id").alias("id"), F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where(F.char_length("line") > longer_than)
    return docs.select(F.col("doc_id").alias("id")), _stars(lines, "line")


def doc_copies(spark: SparkSession, sf_dir: str) -> Graph:
    """Documents with equal texts (by a 256-bit hash, so no text is moved)."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.sha2(F.col("text"), 256).alias("h"))
    return docs.select("id"), _stars(docs, "h")


def page_links(spark: SparkSession, sf_dir: str) -> Graph:
    """Pages (2 * id) and the targets of their links (2 * rank - 1 of the distinct texts)."""
    pages = table(spark, sf_dir, "pages")
    links = pages.select((F.col("page_id") * 2).alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href"))
    from fieldseg.operators.order import numbered

    targets = numbered(links.select("href").distinct(), ["href"], "n").select("href", (F.col("n") * 2 + 1).alias("dst"))
    e = links.join(targets, "href").select("src", "dst").distinct()
    return pages.select((F.col("page_id") * 2).alias("id")).union(targets.select(F.col("dst").alias("id"))), e


def user_sessions(spark: SparkSession, sf_dir: str, gap_minutes: int = 30) -> Graph:
    """Events of a user, each tied to the one before it if it is near in time."""
    ev = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    w = Window.partitionBy("user_id").orderBy("t", "id")
    e = ev.select(F.lag("id").over(w).alias("src"), F.col("id").alias("dst"), (F.col("t") - F.lag("t").over(w)).alias("gap"))
    return ev.select("id"), e.where(F.col("gap") < gap_minutes * 60_000_000).select("src", "dst")


def geo_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, ptr): customers and suppliers point to nations, nations to regions, regions to themselves."""
    region = table(spark, sf_dir, "region").select(F.col("r_regionkey").cast("long").alias("id"), F.col("r_regionkey").cast("long").alias("ptr"))
    nation = table(spark, sf_dir, "nation").select((F.col("n_nationkey") + 100).cast("long").alias("id"), F.col("n_regionkey").cast("long").alias("ptr"))
    customer = table(spark, sf_dir, "customer").select((F.col("c_custkey") * 2 + 1000).alias("id"), (F.col("c_nationkey") + 100).cast("long").alias("ptr"))
    supplier = table(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 2 + 1001).alias("id"), (F.col("s_nationkey") + 100).cast("long").alias("ptr"))
    return region.union(nation).union(customer).union(supplier)


def embedding_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
