"""Graphs made from the given tables: five temporal edge lists, five static graphs, a worked example, and a synthetic scale-up.

Bipartite vertices are 2k and 2k+1; a hierarchy has 4k + kind; turns of a conversation are conv_id * 1000 + turn; links go by a dictionary.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.vectors import nearest
from ..plans.graph import encode_vertices, number_rows, successors, vertices_of

TEMPORAL = ("event_flow", "user_item", "part_flow", "cust_supp", "supp_part")
STATIC = ("order_chain", "turn_chain", "web_links", "knn", "geo_tree")
#: Orders temporal edges of line items; l_orderkey and l_linenumber alone are not unique.
LINE_ORDER = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]


def read(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """Only the columns asked for reach the scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def event_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User to the next user with an event of the same type."""
    e = read(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    e = successors(e, "event_type", ["ts", "event_id"], "user_id", "dst")
    return number_rows(e.select(F.col("user_id").alias("src"), "dst", "ts", "event_id"), ["ts", "event_id"]).select("src", "dst", "seq")


def user_item(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User to the item named in the event's properties."""
    e = read(spark, sf_dir, "events", "event_id", "ts", "user_id", "props")
    e = e.select((F.col("user_id") * 2).alias("src"), (F.get_json_object("props", "$.k").cast("bigint") * 2 + 1).alias("dst"), "ts", "event_id").where("dst IS NOT NULL")
    return number_rows(e, ["ts", "event_id"]).select("src", "dst", "seq")


def part_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part to the next part of the same order."""
    li = read(spark, sf_dir, "lineitem", *LINE_ORDER)
    li = li.withColumn("dst", F.lead("l_partkey").over(Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER))).where("dst IS NOT NULL")
    return number_rows(li.withColumn("src", F.col("l_partkey")), LINE_ORDER).select("src", "dst", "seq")


def cust_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer to supplier, by the date of the order."""
    o = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    both = read(spark, sf_dir, "lineitem", *LINE_ORDER).join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    both = both.withColumn("src", F.col("o_custkey") * 2).withColumn("dst", F.col("l_suppkey") * 2 + 1)
    return number_rows(both, ["o_orderdate", *LINE_ORDER]).select("src", "dst", "seq")


def supp_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier to part, by the date of shipping."""
    li = read(spark, sf_dir, "lineitem", *LINE_ORDER).withColumn("src", F.col("l_suppkey") * 2).withColumn("dst", F.col("l_partkey") * 2 + 1)
    return number_rows(li, LINE_ORDER).select("src", "dst", "seq")


def order_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order to the customer's next order: low degrees, long paths."""
    o = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    return o.select(F.col("o_orderkey").alias("src"), F.lead("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).alias("dst")).where("dst IS NOT NULL")


def turn_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = read(spark, sf_dir, "conversations", "conv_id", "turn")
    me = F.col("conv_id") * 1000 + F.col("turn")
    return c.select(me.alias("src"), F.lead(me).over(Window.partitionBy("conv_id").orderBy("turn")).alias("dst")).where("dst IS NOT NULL")


def link_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page, target) of each page's distinct links, as strings."""
    p = read(spark, sf_dir, "pages", "page_id", "html")
    hrefs = F.array_distinct(F.regexp_extract_all("html", F.lit('<a href="([^"]*)"'), 1))
    return p.select(F.concat(F.lit("p:"), F.col("page_id").cast("string")).alias("page"), F.explode(hrefs).alias("url")).select("page", F.concat(F.lit("u:"), "url").alias("target"))


def web_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = link_names(spark, sf_dir)
    ids = encode_vertices(names, ["page", "target"])
    first, second = ids.select(F.col("key").alias("page"), F.col("id").alias("src")), ids.select(F.col("key").alias("target"), F.col("id").alias("dst"))
    return names.join(first, "page").join(second, "target").select("src", "dst")


def knn(spark: SparkSession, sf_dir: str, k: int = 8) -> DataFrame:
    """Vector to its k nearest by cosine, ties by id: blocks of queries against all rows, best k kept per block."""
    return nearest(read(spark, sf_dir, "embeddings", "vec_id", "embedding"), k).select("src", "dst")


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer and supplier to nation, nation to region."""
    c = read(spark, sf_dir, "customer", "c_custkey", "c_nationkey").select((F.col("c_custkey") * 4).alias("src"), (F.col("c_nationkey").cast("bigint") * 4 + 1).alias("dst"))
    s = read(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey").select((F.col("s_suppkey") * 4 + 2).alias("src"), (F.col("s_nationkey").cast("bigint") * 4 + 1).alias("dst"))
    n = read(spark, sf_dir, "nation", "n_nationkey", "n_regionkey").select((F.col("n_nationkey").cast("bigint") * 4 + 1).alias("src"), (F.col("n_regionkey").cast("bigint") * 4 + 3).alias("dst"))
    return c.unionByName(s).unionByName(n)


#: A worked example of 16 vertices; the batch inserts 4 to 12 and deletes 2 to 1.
EXAMPLE_EDGES = [(2, 1), (2, 8), (4, 14), (1, 3), (1, 5), (1, 10), (8, 9), (8, 10), (8, 15), (12, 14), (14, 15), (3, 4), (5, 6), (9, 10), (15, 16), (10, 16), (16, 6), (6, 2), (7, 11), (11, 13), (13, 7), (13, 12), (11, 4)]
EXAMPLE_BATCH = [(4, 12, "+"), (2, 1, "-")]


def example16(spark: SparkSession) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Vertices, edges and batch of the worked example."""
    return spark.range(1, 17), spark.createDataFrame(EXAMPLE_EDGES, "src bigint, dst bigint"), spark.createDataFrame(EXAMPLE_BATCH, "src bigint, dst bigint, op string")


def synthetic(spark: SparkSession, vertices: int, edges: int, gamma: float = 2.0, seed: int = 1) -> DataFrame:
    """A temporal edge list of any size whose targets are skewed by a power of a uniform hash."""
    u = lambda tag: (F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(f"{seed}:{tag}"), "id")), 1, 8), 16, 10).cast("double") / float(1 << 32))
    return spark.range(edges).select((u("s") * vertices).cast("bigint").alias("src"), (F.pow(u("d"), F.lit(gamma)) * vertices).cast("bigint").alias("dst"), (F.col("id") + 1).alias("seq"))


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (event_flow, user_item, part_flow, cust_supp, supp_part, order_chain, turn_chain, web_links, knn, geo_tree)}


def build(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return BUILDERS[name](spark, sf_dir)


def universe(edges: DataFrame) -> DataFrame:
    """All ids of an edge list: the vertex set does not change while batches are replayed."""
    return vertices_of(edges)
