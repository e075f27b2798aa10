"""Graphs of the experiments, built from the given tables."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from forkline.graph import Graph, dense_ids, graph_of, written
from forkline.sources.tables import load

Builder = Callable[..., Graph]


def _two(df: DataFrame, a: str, b: str) -> DataFrame:
    """Two kinds of keys in one id space: even and odd."""
    return df.select((F.col(a) * 2).alias("a"), (F.col(b) * 2 + 1).alias("b"))


def _next(df: DataFrame, key: str, by: list[str], order: list[str]) -> DataFrame:
    own = W.partitionBy(*by).orderBy(*order)
    return df.select(F.col(key).alias("a"), F.lead(key).over(own).alias("b")).where("b IS NOT NULL")


def _pairs_within(df: DataFrame, member: str, group: str, most: int | None = None) -> DataFrame:
    """Pairs of members of one group. ``most`` leaves out larger groups, whose pairs grow with the square."""
    own = df.select(group, member).repartition(group).distinct()  # one exchange serves the distinct rows and both sides of the join
    if most:
        own = own.join(own.groupBy(group).count().where(F.col("count") <= most).select(group), group, "left_semi")
    return own.select(group, F.col(member).alias("a")).join(own.select(group, F.col(member).alias("b")), group).where("a < b").select("a", "b")


def part_supplier_matrix(spark: SparkSession, sf_dir: str) -> Graph:
    return graph_of(_two(load(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey"]), "l_partkey", "l_suppkey"), "part_supplier_matrix")


def customer_part_matrix(spark: SparkSession, sf_dir: str) -> Graph:
    orders, items = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"])
    return graph_of(_two(orders.join(items, orders.o_orderkey == items.l_orderkey), "o_custkey", "l_partkey"), "customer_part_matrix")


def event_grid(spark: SparkSession, sf_dir: str, grid_width: int = 25) -> Graph:
    cell = load(spark, sf_dir, "events", ["event_id"]).select(F.col("event_id").alias("a"))
    right = cell.where(F.col("a") % grid_width < grid_width - 1).select("a", (F.col("a") + 1).alias("b"))
    down = cell.select("a", (F.col("a") + grid_width).alias("b"))
    return graph_of(right.unionByName(down).join(cell.select(F.col("a").alias("b")), "b", "left_semi").select("a", "b"), "event_grid")


def order_mesh(spark: SparkSession, sf_dir: str) -> Graph:
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority"]).withColumn("year", F.year("o_orderdate"))
    order = ["o_orderdate", "o_orderkey"]
    return graph_of(_next(orders, "o_orderkey", ["o_custkey"], order).unionByName(_next(orders, "o_orderkey", ["o_orderpriority", "year"], order)), "order_mesh")


def part_co_order(spark: SparkSession, sf_dir: str, max_basket: int | None = None) -> Graph:
    return graph_of(_pairs_within(load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]), "l_partkey", "l_orderkey", max_basket), "part_co_order")


def supplier_co_order(spark: SparkSession, sf_dir: str, max_basket: int | None = None) -> Graph:
    return graph_of(_pairs_within(load(spark, sf_dir, "lineitem", ["l_orderkey", "l_suppkey"]), "l_suppkey", "l_orderkey", max_basket), "supplier_co_order")


def bulk_order_part(spark: SparkSession, sf_dir: str, min_quantity: float = 45) -> Graph:
    bulk = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"]).where(F.col("l_quantity") >= min_quantity)
    return graph_of(_two(bulk, "l_orderkey", "l_partkey"), "bulk_order_part")


def bulk_supplier_part(spark: SparkSession, sf_dir: str, min_quantity: float = 45) -> Graph:
    bulk = load(spark, sf_dir, "lineitem", ["l_suppkey", "l_partkey", "l_quantity", "l_returnflag"]).where((F.col("l_quantity") >= min_quantity) & (F.col("l_returnflag") == "R"))
    return graph_of(_two(bulk, "l_suppkey", "l_partkey"), "bulk_supplier_part")


def bulk_order_chain(spark: SparkSession, sf_dir: str, min_quantity: float = 45) -> Graph:
    bulk = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_linenumber", "l_shipdate", "l_quantity"]).where(F.col("l_quantity") >= min_quantity)
    return graph_of(_next(bulk, "l_orderkey", ["l_partkey"], ["l_shipdate", "l_orderkey", "l_linenumber"]), "bulk_order_chain")


def similar_vectors(vectors: DataFrame, min_cosine: float, block_rows: int = 2000) -> DataFrame:
    """Pairs ``(a, b)``, a < b, of ``(id, v)`` with that cosine or more: blocks of vectors meet in pairs, each a matrix product."""
    n = max(1, -(-vectors.count() // block_rows))
    dealt = vectors.withColumn("own", F.pmod(F.xxhash64("id"), F.lit(n)).cast("int"))
    others = F.sequence(F.lit(0), F.lit(n - 1))
    meeting = dealt.withColumn("other", F.explode(others)).select("id", "v", "own", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"))

    def product(t: pd.DataFrame) -> pd.DataFrame:
        p, q = t["p"].iat[0], t["q"].iat[0]
        x, y = t[t["own"] == p], t[t["own"] == q]
        m, k = (np.array(z["v"].tolist(), dtype=float) for z in (x, y))
        cosine = (m @ k.T) / (np.linalg.norm(m, axis=1)[:, None] * np.linalg.norm(k, axis=1)[None])
        i, j = np.nonzero(cosine >= min_cosine)
        a, b = x["id"].to_numpy()[i], y["id"].to_numpy()[j]
        keep = a != b if p != q else a < b
        return pd.DataFrame({"a": np.minimum(a, b)[keep], "b": np.maximum(a, b)[keep]})

    return meeting.groupBy("p", "q").applyInPandas(product, "a bigint, b bigint")


def embedding_neighbors(spark: SparkSession, sf_dir: str, min_cosine: float = 0.35) -> Graph:
    vectors = load(spark, sf_dir, "embeddings", ["vec_id", "embedding"]).select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    return graph_of(similar_vectors(vectors, min_cosine), "embedding_neighbors")


def document_lines(spark: SparkSession, sf_dir: str, min_line_chars: int = 60, max_doc_freq: int = 20) -> Graph:
    """Documents that share a long line: all pairs of those that share one with few, else each with the smallest id that has it."""
    lines = load(spark, sf_dir, "documents", ["doc_id", "text"]).select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.length("line") >= min_line_chars).distinct()
    shared = lines.groupBy("line").agg(F.count("*").alias("n"), F.min("doc_id").alias("b")).where("n >= 2")
    few = lines.join(shared.where(F.col("n") <= max_doc_freq).select("line"), "line", "left_semi")
    star = lines.join(shared.where(F.col("n") > max_doc_freq), "line").select(F.col("doc_id").alias("a"), "b")
    return graph_of(_pairs_within(few, "doc_id", "line").unionByName(star), "document_lines")


def page_links(spark: SparkSession, sf_dir: str) -> Graph:
    hrefs = load(spark, sf_dir, "pages", ["page_id", "html"]).select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).distinct()
    shared = hrefs.join(hrefs.groupBy("href").count().where("count >= 2").select("href"), "href", "left_semi")
    return graph_of(_two(shared.join(dense_ids(shared, "href"), "href"), "page_id", "id"), "page_links")


def page_domains(spark: SparkSession, sf_dir: str) -> Graph:
    domains = load(spark, sf_dir, "pages", ["page_id", "url"]).select("page_id", F.regexp_extract("url", r"^[a-z]+://(?:(?:www|m|blog)\.)?([^/:?#]+)", 1).alias("domain")).where("domain <> ''")
    return graph_of(_two(domains.join(dense_ids(domains, "domain"), "domain"), "page_id", "id"), "page_domains")


def user_activity(spark: SparkSession, sf_dir: str) -> Graph:
    hours = load(spark, sf_dir, "events", ["user_id", "ts"]).select("user_id", F.expr("timestampdiff(HOUR, TIMESTAMP_NTZ '1970-01-01 00:00:00', ts)").alias("hour"))
    return graph_of(_two(hours, "user_id", "hour"), "user_activity")


def event_user_chain(spark: SparkSession, sf_dir: str) -> Graph:
    return graph_of(_next(load(spark, sf_dir, "events", ["event_id", "user_id", "ts"]), "event_id", ["user_id"], ["ts", "event_id"]), "event_user_chain")


def _order_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _next(load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate"]), "o_orderkey", ["o_custkey"], ["o_orderdate", "o_orderkey"])


def customer_order_chain(spark: SparkSession, sf_dir: str) -> Graph:
    return graph_of(_order_chain(spark, sf_dir), "customer_order_chain")


def directed_order_chain(spark: SparkSession, sf_dir: str) -> Graph:
    return graph_of(_order_chain(spark, sf_dir), "directed_order_chain", directed=True)


def conversation_turns(spark: SparkSession, sf_dir: str) -> Graph:
    turns = load(spark, sf_dir, "conversations", ["conv_id", "turn"]).select("conv_id", "turn", (F.col("conv_id") * 4096 + F.col("turn")).alias("key")).distinct()
    return graph_of(_next(turns, "key", ["conv_id"], ["turn"]), "conversation_turns")


def _coded(df: DataFrame, a: str, a_kind: int, b: str, b_kind: int) -> DataFrame:
    return df.select((F.col(a).cast("bigint") * 4 + a_kind).alias("a"), (F.col(b).cast("bigint") * 4 + b_kind).alias("b"))


def geo_tree(spark: SparkSession, sf_dir: str) -> Graph:
    """Orders, customers, nations, regions; an id is the key times 4 plus the kind, 0 to 3."""
    pairs = (
        _coded(load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), "o_orderkey", 0, "o_custkey", 1)
        .unionByName(_coded(load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]), "c_custkey", 1, "c_nationkey", 2))
        .unionByName(_coded(load(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"]), "n_nationkey", 2, "n_regionkey", 3))
    )
    return graph_of(pairs, "geo_tree")


def supplier_geo_tree(spark: SparkSession, sf_dir: str) -> Graph:
    suppliers = load(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"])
    nations = load(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"]).join(suppliers.select(F.col("s_nationkey").alias("n_nationkey")), "n_nationkey", "left_semi")
    return graph_of(_coded(suppliers, "s_suppkey", 0, "s_nationkey", 2).unionByName(_coded(nations, "n_nationkey", 2, "n_regionkey", 3)), "supplier_geo_tree")


def benchmark_overlap(spark: SparkSession, sf_dir: str, gram: int = 8, quality: int | None = None) -> Graph:
    def grams(df: DataFrame, key: str) -> DataFrame:
        words = df.select(key, F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+"), lambda w: w != "").alias("w")).where(F.size("w") >= gram)
        cut = F.transform(F.sequence(F.lit(1), F.size("w") - gram + 1), lambda i: F.array_join(F.slice("w", i, gram), " "))
        return words.select(key, F.explode(cut).alias("gram")).distinct()

    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    if quality is not None:
        docs = docs.join(load(spark, sf_dir, "labels").where(F.col("quality") == quality).select("doc_id"), "doc_id", "left_semi")
    return graph_of(_two(grams(docs, "doc_id").join(grams(load(spark, sf_dir, "benchmark"), "item_id"), "gram").select("doc_id", "item_id").distinct(), "doc_id", "item_id"), "benchmark_overlap")


def with_isolated(spark: SparkSession, sf_dir: str) -> Graph:
    """``bulk_order_part`` with every part as a vertex."""
    bulk = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"]).where("l_quantity >= 45")
    return graph_of(_two(bulk, "l_orderkey", "l_partkey"), "with_isolated", vertices=load(spark, sf_dir, "part", ["p_partkey"]).select((F.col("p_partkey") * 2 + 1).alias("id")))


WORKLOADS: dict[str, Builder] = {
    f.__name__: f
    for f in (
        part_supplier_matrix, customer_part_matrix, event_grid, order_mesh, part_co_order, supplier_co_order, bulk_order_part, bulk_supplier_part, bulk_order_chain, embedding_neighbors,
        document_lines, page_links, page_domains, user_activity, event_user_chain, customer_order_chain, conversation_turns, geo_tree, supplier_geo_tree, benchmark_overlap, with_isolated, directed_order_chain,
    )
}


def build(name: str, spark: SparkSession, sf_dir: str, **params) -> Graph:
    """A workload with its edges and vertices written once, so that iterations don't rebuild them."""
    return written(WORKLOADS[name](spark, sf_dir, **params))
