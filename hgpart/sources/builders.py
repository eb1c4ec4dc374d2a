"""Hypergraphs from ordinary tables: one builder per experiment workload."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hgpart.model import Hypergraph, Limits, assign_ids
from hgpart.plans.checkpoints import materialize

#: Node ids of the layered network: kind * LAYER + key.
LAYER = 1_000_000_000_000
#: Vectors of a block of the exact nearest neighbours.
KNN_ROWS = 2048


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _first_is_source(rows: DataFrame, first: DataFrame) -> DataFrame:
    """rows (e, n) with the node named by first (e, head) as source and the others as destinations."""
    return rows.join(first, "e").select("e", "n", (F.col("n") == F.col("head")).alias("is_src"), (F.col("n") != F.col("head")).alias("is_dst"))


def basket(spark: SparkSession, sf_dir: str) -> Hypergraph:
    lines = _table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").cast("bigint").alias("e"), F.col("l_partkey").cast("bigint").alias("n"), "l_linenumber", F.col("l_quantity").cast("bigint").alias("w"))
    # an order's lines are shuffled once: its first line is found where they meet, and so are lines of the same part
    headed = lines.filter("e is not null").withColumn("head", F.first("n").over(Window.partitionBy("e").orderBy("l_linenumber", "n")))
    source = F.coalesce(F.col("n") == F.col("head"), F.lit(False))
    pins = headed.groupBy("e", "n", "head").agg(F.lit(1)).select("e", "n", source.alias("is_src"), (~source).alias("is_dst"))
    edges = lines.groupBy("e").agg(F.sum("w").alias("w")).select("e", "w", F.lit(1).alias("mult"))
    return Hypergraph(pins, edges, _table(spark, sf_dir, "part").select(F.col("p_partkey").cast("bigint").alias("n"), F.lit(1).cast("bigint").alias("size")))


def copurchase(spark: SparkSession, sf_dir: str) -> Hypergraph:
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("e"))
    orders = _table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("n"), "o_orderdate")
    bought = lines.join(orders, "l_orderkey")
    first = bought.groupBy("e").agg(F.min(F.struct("o_orderdate", "n")).getField("n").alias("head"))
    weights = _table(spark, sf_dir, "part").select(F.col("p_partkey").alias("e"), F.col("p_size").alias("w")).join(first.select("e"), "e", "left_semi")
    return Hypergraph.from_pins(_first_is_source(bought.select("e", "n").distinct(), first), weights, _table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("n")))


def _all_destinations(rows: DataFrame) -> DataFrame:
    return rows.select("e", "n", F.lit(False).alias("is_src"), F.lit(True).alias("is_dst")).distinct()


def sourcing(spark: SparkSession, sf_dir: str) -> Hypergraph:
    lines = _table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("e"), F.col("l_partkey").alias("n"))
    return Hypergraph.from_pins(_all_destinations(lines), None, _table(spark, sf_dir, "part").select(F.col("p_partkey").alias("n")))


def suppliers(spark: SparkSession, sf_dir: str) -> Hypergraph:
    lines = _table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("e"), F.col("l_suppkey").alias("n"))
    weights = _table(spark, sf_dir, "part").select(F.col("p_partkey").alias("e"), F.col("p_size").alias("w")).join(lines.select("e").distinct(), "e", "left_semi")
    return Hypergraph.from_pins(_all_destinations(lines), weights, _table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("n")))


def _by_tokens(rows: DataFrame, nodes: DataFrame, least: int = 2, most: int = 32) -> Hypergraph:
    """rows (n, text): a hyperedge for each token that `least` to `most` nodes hold."""
    # written once: texts would be split again for each use
    tokens = materialize(rows.select("n", F.explode(F.split(F.lower("text"), r"[^\p{L}0-9]+")).alias("token")).filter("token <> ''").distinct(), "tokens")
    df = tokens.groupBy("token").agg(F.count(F.lit(1)).alias("df"), F.min("n").alias("head")).filter(F.col("df").between(least, most))
    ids = assign_ids(df, "token", "e").join(df, "token")
    pins = tokens.join(ids.select("token", "e", "head"), "token").select("e", "n", (F.col("n") == F.col("head")).alias("is_src"), (F.col("n") != F.col("head")).alias("is_dst"))
    return Hypergraph.from_pins(materialize(pins, "pins"), None, nodes)


def terms(spark: SparkSession, sf_dir: str) -> Hypergraph:
    docs = _table(spark, sf_dir, "documents").select(F.col("doc_id").alias("n"), "text")
    return _by_tokens(docs, docs.select("n").distinct())


def dialog(spark: SparkSession, sf_dir: str) -> Hypergraph:
    turns = _table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("n"), "text")
    return _by_tokens(turns, turns.select("n").distinct())


def links(spark: SparkSession, sf_dir: str) -> Hypergraph:
    pages = _table(spark, sf_dir, "pages")
    hrefs = pages.select(F.col("page_id").alias("n"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).distinct()
    hrefs = materialize(hrefs, "hrefs")  # written once: pages would be searched again for each use
    first = hrefs.groupBy("href").agg(F.min("n").alias("head"))
    ids = assign_ids(first, "href", "e").join(first, "href")
    pins = hrefs.join(ids, "href").select("e", "n", (F.col("n") == F.col("head")).alias("is_src"), (F.col("n") != F.col("head")).alias("is_dst"))
    return Hypergraph.from_pins(pins, None, pages.select(F.col("page_id").alias("n")))


def cohort(spark: SparkSession, sf_dir: str) -> Hypergraph:
    events = _table(spark, sf_dir, "events").select(F.col("user_id").alias("n"), "ts", F.date_trunc("hour", "ts").alias("hour"), "event_type", "event_id")
    per = events.groupBy("hour", "event_type").agg(F.min(F.struct("ts", "event_id", "n")).getField("n").alias("head"), F.count(F.lit(1)).alias("w"))
    keyed = per.withColumn("key", F.concat_ws("|", F.date_format("hour", "yyyy-MM-dd HH"), "event_type"))
    ids = assign_ids(keyed, "key", "e").join(keyed, "key")
    pins = _first_is_source(events.select("hour", "event_type", "n").distinct().join(ids, ["hour", "event_type"]).select("e", "n"), ids.select("e", "head"))
    return Hypergraph.from_pins(pins, ids.select("e", "w"), events.select("n").distinct())


def trade(spark: SparkSession, sf_dir: str) -> Hypergraph:
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("e"), "l_suppkey")
    sellers = lines.join(_table(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).select("e", F.col("s_nationkey").alias("n"), F.lit(True).alias("is_src"), F.lit(False).alias("is_dst"))
    orders = _table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(_table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    buyers = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("e", F.col("c_nationkey").alias("n"), F.lit(False).alias("is_src"), F.lit(True).alias("is_dst"))
    weights = lines.groupBy("e").agg(F.count(F.lit(1)).alias("w"))
    return Hypergraph.from_pins(sellers.unionByName(buyers), weights, _table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("n")))


def nearest(vectors: DataFrame, k: int = 8, rows: int = KNN_ROWS) -> DataFrame:
    """(vec_id, near) of each vector's k nearest by dot product, the smaller id on ties.

    Exact at any size: vectors are dealt to blocks of about `rows`; each block of queries meets each block of the base in a task of
    its own, which gives the k best there, and the best of these are kept."""
    import numpy as np
    import pandas as pd

    blocks = max(1, -(-vectors.count() // rows))
    given = vectors.select("vec_id", "embedding").withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)))
    every = F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(blocks - 1).cast("bigint")))
    queries, base = given.withColumnRenamed("b", "i").withColumn("j", every), given.withColumnRenamed("b", "j").withColumn("i", every)

    def search(asked, held):
        out = []
        if len(asked) and len(held):
            ids, matrix = held["vec_id"].to_numpy(), np.array(held["embedding"].tolist(), np.float64)
            scores = np.round(np.array(asked["embedding"].tolist(), np.float64) @ matrix.T, 6)
            for own, row in zip(asked["vec_id"], scores):
                order = np.lexsort((ids, -row))[: k + 1]
                out += [(own, ids[x], row[x]) for x in order if ids[x] != own][:k]
        return pd.DataFrame(out, columns=["vec_id", "near", "score"])

    found = queries.groupBy("i", "j").cogroup(base.groupBy("i", "j")).applyInPandas(search, "vec_id long, near long, score double")
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.col("score").desc(), "near"))
    return found.withColumn("r", rank).filter(F.col("r") <= k).select("vec_id", "near")


def knn(spark: SparkSession, sf_dir: str) -> Hypergraph:
    vectors = _table(spark, sf_dir, "embeddings")
    near = nearest(vectors)
    own = vectors.select(F.col("vec_id").alias("e"), F.col("vec_id").alias("n"), F.lit(True).alias("is_src"), F.lit(False).alias("is_dst"))
    pins = own.unionByName(near.select(F.col("vec_id").alias("e"), F.col("near").alias("n"), F.lit(False).alias("is_src"), F.lit(True).alias("is_dst")))
    return Hypergraph.from_pins(pins, None, vectors.select(F.col("vec_id").alias("n")))


def layered(spark: SparkSession, sf_dir: str) -> Hypergraph:
    """nation -> customers, customer -> orders, order -> parts; ids of nodes and hyperedges are kind * LAYER + key."""
    customers = _table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    orders = _table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    hops = [
        (0, customers.select(F.col("c_nationkey").alias("a"), F.col("c_custkey").alias("b"))),
        (1, orders.select(F.col("o_custkey").alias("a"), F.col("o_orderkey").alias("b"))),
        (2, lines.select(F.col("l_orderkey").alias("a"), F.col("l_partkey").alias("b"))),
    ]
    pins = None
    for k, hop in hops:
        at = lambda c, kind: (F.col(c).cast("bigint") + kind * LAYER)
        ends = F.array(F.struct(at("a", k).alias("n"), F.lit(True).alias("is_src"), F.lit(False).alias("is_dst")), F.struct(at("b", k + 1).alias("n"), F.lit(False).alias("is_src"), F.lit(True).alias("is_dst")))
        one = hop.select(at("a", k).alias("e"), F.explode(ends).alias("x")).select("e", "x.*")
        pins = one if pins is None else pins.unionByName(one)
    keys = [(_table(spark, sf_dir, t), c) for t, c in (("nation", "n_nationkey"), ("customer", "c_custkey"), ("orders", "o_orderkey"), ("part", "p_partkey"))]
    nodes = None
    for k, (t, c) in enumerate(keys):
        one = t.select((F.col(c).cast("bigint") + k * LAYER).alias("n"))
        nodes = one if nodes is None else nodes.unionByName(one)
    return Hypergraph.from_pins(pins, None, nodes)


BUILDERS: dict[str, Callable[[SparkSession, str], Hypergraph]] = {
    f.__name__: f for f in (basket, copurchase, sourcing, suppliers, terms, dialog, links, cohort, trade, knn, layered)
}
#: Limits of each workload: nodes of a partition, and the inbound limit as a multiple (in hundredths) of the largest in-degree.
REGIMES: dict[str, tuple[int, int]] = {
    "basket": (16, 400), "copurchase": (16, 200), "sourcing": (64, 110), "suppliers": (4, 110), "terms": (16, 200), "dialog": (8, 150),
    "links": (16, 400), "cohort": (8, 300), "trade": (8, 105), "knn": (16, 400), "layered": (32, 200),
}


def limits_of(name: str, hg: Hypergraph) -> Limits:
    """Limits that bind without making a single node infeasible: the second is relative to the largest in-degree."""
    nodes, share = REGIMES[name]
    most = hg.pins.filter("is_dst").groupBy("n").agg(F.count(F.lit(1)).alias("d")).agg(F.max("d")).first()[0] or 0
    return Limits(nodes, share * most // 100)
