"""Cost and quality measures of a partitioning."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.model import Hypergraph, Limits
from hgpart.operators.moves import partition_loads, partition_pins


def spans(hg: Hypergraph, assign: DataFrame) -> DataFrame:
    """(e, parts): partitions that each hyperedge touches."""
    return hg.pins.join(assign, "n").select("e", "p").distinct().groupBy("e").agg(F.count(F.lit(1)).alias("parts"))


def connectivity(hg: Hypergraph, assign: DataFrame) -> DataFrame:
    return spans(hg, assign).join(hg.edges, "e").agg(F.coalesce(F.sum(F.col("w") * (F.col("parts") - 1)), F.lit(0)).alias("connectivity"))


def cut_measures(hg: Hypergraph, assign: DataFrame) -> DataFrame:
    """One row: weight of cut hyperedges, sum of external degrees, weight of uncut ones."""
    s = spans(hg, assign).join(hg.edges, "e")
    cut = F.col("parts") > 1
    zero = lambda c: F.coalesce(c, F.lit(0))
    return s.agg(zero(F.sum(F.when(cut, F.col("w")))).alias("cut_weight"), zero(F.sum(F.when(cut, F.col("w") * F.col("parts")))).alias("external_degree"), zero(F.sum(F.when(~cut, F.col("w")))).alias("absorbed_weight"))


def partition_count(hg: Hypergraph, assign: DataFrame, limits: Limits) -> DataFrame:
    """One row: partitions, and the fewest that the size limit allows."""
    total = hg.nodes.agg(F.ceil(F.sum("size") / F.lit(limits.max_nodes)).cast("bigint").alias("lower_bound"))
    return assign.agg(F.countDistinct("p").alias("n_parts")).crossJoin(F.broadcast(total))  # one row


def constraint_report(hg: Hypergraph, assign: DataFrame, limits: Limits) -> DataFrame:
    """(p, size, inbound, free_nodes, free_inbound, broken) of every partition."""
    loads = partition_loads(hg, assign, partition_pins(hg, assign, limits))
    return loads.select(
        "p", "size", "inbound", (F.lit(limits.max_nodes) - F.col("size")).alias("free_nodes"), (F.lit(limits.max_inbound) - F.col("inbound")).alias("free_inbound"),
        ((F.col("size") > limits.max_nodes) | (F.col("inbound") > limits.max_inbound)).alias("broken"),
    )


def summary(hg: Hypergraph, assign: DataFrame, limits: Limits) -> DataFrame:
    """One row: connectivity, partitions, largest size and inbound count, broken limits."""
    per = constraint_report(hg, assign, limits).agg(
        F.count(F.lit(1)).alias("n_parts"), F.max("size").alias("max_size"), F.max("inbound").alias("max_inbound"), F.count_if("broken").alias("n_broken")
    )
    return connectivity(hg, assign).crossJoin(F.broadcast(per))  # one row


def pair_volume(hg: Hypergraph) -> DataFrame:
    """One row: ordered neighbour pairs, and bytes of neighbours alone (8 each) and of bins with weights (16)."""
    from hgpart.model import neighbors

    n = neighbors(hg).agg(F.count(F.lit(1)).alias("pairs"))
    return n.select("pairs", (F.col("pairs") * 8).alias("neighbour_bytes"), (F.col("pairs") * 16).alias("bin_bytes"))
