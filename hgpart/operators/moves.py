"""Refinement, first part: pins of each partition, gains, and each node's own best move."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.model import Hypergraph, Limits, argmax_by
from hgpart.operators import blocks
from hgpart.plans.checkpoints import materialize, small


def partition_pins(hg: Hypergraph, assign: DataFrame, limits: Limits = Limits()) -> DataFrame:
    """(e, p, cnt, cnt_in): pins of e in p, and those that count towards the limit. Only what is not zero."""
    return hg.pins.join(small(assign), "n").groupBy("e", "p").agg(F.count(F.lit(1)).alias("cnt"), F.count_if(limits.bound()).alias("cnt_in"))


def partition_loads(hg: Hypergraph, assign: DataFrame, pe: DataFrame) -> DataFrame:
    """(p, size, inbound) of every partition."""
    sizes = hg.nodes.join(assign, "n").groupBy("p").agg(F.sum("size").alias("size"))
    inbound = pe.filter("cnt_in > 0").join(hg.edges, "e").groupBy("p").agg(F.sum("mult").alias("inbound"))
    return sizes.join(inbound, "p", "left").select("p", "size", F.coalesce("inbound", F.lit(0)).alias("inbound"))


def savings(hg: Hypergraph, assign: DataFrame, pe: DataFrame) -> DataFrame:
    """(n, ps, saving, total): weight of hyperedges that leave n's partition with n, and of all of n's."""
    own = hg.pins.select("e", "n").join(small(hg.edges).select("e", "w"), "e").join(small(assign), "n").join(pe.select("e", "p", "cnt"), ["e", "p"])
    return own.groupBy("n", F.col("p").alias("ps")).agg(F.sum(F.when(F.col("cnt") == 1, F.col("w")).otherwise(0)).alias("saving"), F.sum("w").alias("total"))


def gains(hg: Hypergraph, assign: DataFrame, pe: DataFrame) -> DataFrame:
    """(n, ps, p, gain) for partitions p that share a hyperedge with n.

    The loss of moving to p is n's whole weight less that of its hyperedges which p already holds, so only
    partitions that touch n are listed; any other has no positive gain."""
    touch = (
        hg.weighted_pins.select("e", "n", "w").join(pe.select("e", "p"), "e").groupBy("n", "p").agg(F.sum("w").alias("touch"))
    )
    return savings(hg, assign, pe).join(touch, "n").filter("p <> ps").select("n", "ps", "p", (F.col("saving") - F.col("total") + F.col("touch")).alias("gain"))


def propose_moves(hg: Hypergraph, assign: DataFrame, pe: DataFrame, limits: Limits, admit: str = "not_full", min_gain: int = 1) -> DataFrame:
    """(n, ps, pd, gain): the best move of each node, the larger partition on ties.

    admit="not_full" excludes partitions of full size; "fits" those that the node would overfill."""
    if min_gain < 1:
        raise ValueError("min_gain must be at least 1: partitions that share nothing with a node are not looked at")
    sizes = hg.nodes.join(assign, "n").groupBy("p").agg(F.sum("size").alias("psize"))
    if not blocks.take(hg):
        return _joined_moves(hg, assign, pe, limits, admit, min_gain, sizes)
    room = pe.select("e", "p").join(sizes, "p").select("e", F.col("p").alias("c"), F.col("psize").alias("a"), F.lit(0).alias("b"), F.lit(True).alias("f"))
    if admit != "fits":
        room = room.filter(F.col("a") < limits.max_nodes)
    base = savings(hg, assign, pe).join(hg.nodes, "n").select("n", F.col("size").alias("a"), (F.col("saving") - F.col("total")).alias("b"), F.col("ps").alias("f"))
    base = materialize(base, "base")
    most = limits.max_nodes if admit == "fits" else None

    def solve(block):
        def valid(rows, cols, sums, shared):
            fits = sums + block.b[rows] >= min_gain
            return fits if most is None else fits & (block.a[rows] + block.col_a[cols] <= most)

        return block.best(block.f, valid, False)

    best = blocks.best_columns(hg.pins.select("e", "n").join(small(base), "n"), room, hg.edges, solve)
    return best.join(base, "n").select("n", F.col("f").alias("ps"), F.col("c").alias("pd"), (F.col("score") + F.col("b")).alias("gain"))


def _joined_moves(hg: Hypergraph, assign: DataFrame, pe: DataFrame, limits: Limits, admit: str, min_gain: int, sizes: DataFrame) -> DataFrame:
    """The same with the options written out, for weights and ids that blocks do not take."""
    options = gains(hg, assign, pe).filter(F.col("gain") >= min_gain)
    if admit == "fits":
        options = options.join(sizes, "p").join(hg.nodes, "n").filter(F.col("psize") + F.col("size") <= limits.max_nodes)
    else:
        options = options.join(sizes.filter(F.col("psize") >= limits.max_nodes), "p", "left_anti")
    best = argmax_by(options, "n", "gain", "p")
    return best.join(assign.withColumnRenamed("p", "ps"), "n").select("n", "ps", F.col("p").alias("pd"), "gain")
