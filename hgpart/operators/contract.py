"""Coarse hypergraphs from matched pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.model import Hypergraph
from hgpart.plans.checkpoints import small


def coarse_map(nodes: DataFrame, matched: DataFrame) -> DataFrame:
    """(n, c): the smaller id of a pair stands for both."""
    return nodes.select("n").join(matched, "n", "left").select("n", F.least("n", F.coalesce("mate", "n")).alias("c"))


def contract(hg: Hypergraph, gamma: DataFrame) -> Hypergraph:
    """Pins mapped to coarse nodes and merged, sizes added up; hyperedges left with one pin stay, as they still bound."""
    pins = hg.pins.join(small(gamma), "n").groupBy("e", F.col("c").alias("n")).agg(F.bool_or("is_src").alias("is_src"), F.bool_or("is_dst").alias("is_dst"))
    nodes = hg.nodes.join(gamma, "n").groupBy(F.col("c").alias("n")).agg(F.sum("size").alias("size"))
    return Hypergraph(pins.select("e", "n", "is_src", "is_dst"), hg.edges, nodes)


def contract_neighbors(nbrs: DataFrame, gamma: DataFrame) -> DataFrame:
    a = gamma.select("n", F.col("c").alias("cn"))
    b = gamma.select(F.col("n").alias("m"), F.col("c").alias("cm"))
    return nbrs.join(a, "n").join(b, "m").filter("cn <> cm").select(F.col("cn").alias("n"), F.col("cm").alias("m")).distinct()
