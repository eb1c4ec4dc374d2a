"""Refinement, second part: moves in sequence, their gains there, and which states are valid.

Nothing materialises a state: each move makes signed events for the sizes and in-sets that it changes,
and running sums over these tell every partition's load after every move.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hgpart.model import Hypergraph, Limits, global_rank, global_scan, segmented_scan


def sequence_moves(moves: DataFrame) -> DataFrame:
    """(idx, n, ps, pd, gain): by falling gain, the smaller node first on ties."""
    return global_rank(moves, F.col("gain").desc(), F.col("n").asc()).select("idx", "n", "ps", "pd", "gain")


def _moved_pins(hg: Hypergraph, seq: DataFrame) -> DataFrame:
    return hg.weighted_pins.select("e", "n", "w", "mult", "is_src", "is_dst").join(seq.select("idx", "n", "ps", "pd"), "n")


_TERMS = {
    # change of the four indicators between the start and the moment of the move, each for itself
    "independent": "w * (CASE WHEN ks + a_s = 1 THEN 1 ELSE 0 END - CASE WHEN ks = 1 THEN 1 ELSE 0 END - CASE WHEN kd + a_d = 0 THEN 1 ELSE 0 END + CASE WHEN kd = 0 THEN 1 ELSE 0 END)",
    # either reason counts once: kept for comparison only, it misses moves with both
    "literal_or": "w * (CASE WHEN (ks > 1 AND ks + a_s = 1) OR (kd = 0 AND kd + a_d > 0) THEN 1 ELSE 0 END - CASE WHEN (kd > 0 AND kd + a_d = 0) OR (ks = 1 AND ks + a_s > 1) THEN 1 ELSE 0 END)",
}


def sequence_gains(hg: Hypergraph, seq: DataFrame, pe: DataFrame, method: str = "scan", form: str = "independent") -> DataFrame:
    """(idx, n, ps, pd, gain, seq_gain): seq_gain assumes all earlier moves made.

    "scan" counts earlier arrivals by running sums per (e, p); "pairs" by joining moved pins with each other."""
    moved = _moved_pins(hg, seq)
    if method == "scan":
        events = moved.select("e", "idx", "n", "w", F.explode(F.array(F.struct(F.col("ps").alias("p"), F.lit(-1).alias("d")), F.struct(F.col("pd").alias("p"), F.lit(1).alias("d")))).alias("x"))
        earlier = Window.partitionBy("e", "p").orderBy("idx").rowsBetween(Window.unboundedPreceding, -1)
        counted = events.select("e", "idx", "n", "w", "x.p", "x.d").withColumn("a", F.coalesce(F.sum("d").over(earlier), F.lit(0)))
        counted = counted.join(pe.select("e", "p", "cnt"), ["e", "p"], "left").withColumn("k", F.coalesce("cnt", F.lit(0)))
        sides = counted.groupBy("e", "idx", "w").agg(
            *[F.max(F.when(F.col("d") == d, F.col(c))).alias(name) for d, c, name in ((-1, "k", "ks"), (-1, "a", "a_s"), (1, "k", "kd"), (1, "a", "a_d"))]
        )
    else:
        other = moved.select("e", F.col("idx").alias("i2"), F.col("ps").alias("ps2"), F.col("pd").alias("pd2"))
        pairs = moved.join(other, "e").filter("i2 < idx")
        net = lambda p: F.sum(F.when(F.col("pd2") == F.col(p), 1).otherwise(0) - F.when(F.col("ps2") == F.col(p), 1).otherwise(0))
        counts = pairs.groupBy("e", "idx").agg(net("ps").alias("a_s"), net("pd").alias("a_d"))
        zero = lambda c: F.coalesce(F.col(c), F.lit(0)).alias(c)
        sides = (
            moved.join(counts, ["e", "idx"], "left")
            .join(pe.select("e", F.col("p").alias("ps"), F.col("cnt").alias("ks")), ["e", "ps"], "left")
            .join(pe.select("e", F.col("p").alias("pd"), F.col("cnt").alias("kd")), ["e", "pd"], "left")
            .select("e", "idx", "w", zero("a_s"), zero("a_d"), zero("ks"), zero("kd"))
        )
    change = sides.groupBy("idx").agg(F.sum(F.expr(_TERMS[form])).alias("change"))
    return seq.join(change, "idx", "left").select("idx", "n", "ps", "pd", "gain", (F.col("gain") + F.coalesce("change", F.lit(0))).alias("seq_gain"))


def size_events(hg: Hypergraph, seq: DataFrame, block: int | None = None) -> DataFrame:
    """(p, idx, delta, total): changes of partition sizes and their running sums; block as in model.segmented_scan."""
    rows = seq.join(hg.nodes, "n").select("idx", F.explode(F.array(F.struct(F.col("ps").alias("p"), (-F.col("size")).alias("delta")), F.struct(F.col("pd").alias("p"), F.col("size").alias("delta")))).alias("x")).select("x.p", "idx", "x.delta")
    return segmented_scan(rows, ["p"], "idx", "delta", "total", block)


def inbound_events(hg: Hypergraph, seq: DataFrame, limits: Limits = Limits()) -> DataFrame:
    """(p, e, idx, delta, total): changes of pins that count towards the limit."""
    rows = _moved_pins(hg, seq).filter(limits.bound()).select("e", "mult", "idx", F.explode(F.array(F.struct(F.col("ps").alias("p"), F.lit(-1).cast("bigint").alias("delta")), F.struct(F.col("pd").alias("p"), F.lit(1).cast("bigint").alias("delta")))).alias("x"))
    return segmented_scan(rows.select("x.p", "e", "mult", "idx", "x.delta"), ["p", "e"], "idx", "delta", "total")


def inbound_transitions(events: DataFrame, pe: DataFrame, block: int | None = None) -> DataFrame:
    """(p, idx, delta, total): changes of distinct inbound hyperedges, where a pin count leaves or reaches 0."""
    known = events.join(pe.select("e", "p", "cnt_in"), ["e", "p"], "left").withColumn("now", F.coalesce("cnt_in", F.lit(0)) + F.col("total"))
    step = F.when((F.col("now") > 0) & (F.col("now") - F.col("delta") == 0), F.col("mult")).when((F.col("now") == 0) & (F.col("now") - F.col("delta") > 0), -F.col("mult"))
    rows = known.withColumn("step", step).filter("step is not null").groupBy("p", "idx").agg(F.sum("step").alias("delta"))
    return segmented_scan(rows, ["p"], "idx", "delta", "total", block)


def _before(bad: DataFrame, block: int | None) -> DataFrame:
    """bad(p, idx, bad) with `before`: bad of the same p's event before, null at its first."""
    by_idx = lambda *keys: Window.partitionBy(*keys).orderBy("idx")
    if not block:
        return bad.withColumn("before", F.lag("bad").over(by_idx("p")))
    blocked = bad.withColumn("v__block", F.floor(F.col("idx") / F.lit(block)).cast("bigint"))
    ends = blocked.groupBy("p", "v__block").agg(F.max(F.struct("idx", "bad")).getField("bad").alias("v__end"))
    handed = ends.select("p", "v__block", F.lag("v__end").over(Window.partitionBy("p").orderBy("v__block")).alias("v__end"))
    own = blocked.withColumn("before", F.lag("bad").over(by_idx("p", "v__block"))).join(handed, ["p", "v__block"])
    return own.withColumn("before", F.coalesce("before", "v__end")).drop("v__block", "v__end")


def validity_flips(sizes: DataFrame, inbound: DataFrame, loads: DataFrame, limits: Limits, block: int | None = None) -> DataFrame:
    """(kind, p, idx, flip): +1 where a partition starts to break a limit, -1 where it stops."""
    out = None
    for kind, events, start, most in (("size", sizes, "size", limits.max_nodes), ("inbound", inbound, "inbound", limits.max_inbound)):
        load = events.select("p", "idx", "total").join(loads.select("p", F.col(start).alias("start")), "p", "left").withColumn("start", F.coalesce("start", F.lit(0)))
        bad = load.withColumn("bad", (F.col("start") + F.col("total") > most).cast("int"))
        before = F.coalesce(F.col("before"), (F.col("start") > most).cast("int"))
        one = _before(bad, block).withColumn("flip", F.col("bad") - before).filter("flip <> 0").select(F.lit(kind).alias("kind"), "p", "idx", "flip")
        out = one if out is None else out.unionByName(one)
    return out


def active_violations(seq: DataFrame, flips: DataFrame, loads: DataFrame, limits: Limits) -> DataFrame:
    """(idx, viol): limits broken after each move."""
    at_start = loads.agg(F.sum((F.col("size") > limits.max_nodes).cast("int") + (F.col("inbound") > limits.max_inbound).cast("int")).alias("start"))
    per = flips.groupBy("idx").agg(F.sum("flip").alias("flip"))
    rows = seq.select("idx").join(per, "idx", "left").withColumn("flip", F.coalesce("flip", F.lit(0)))
    scanned = global_scan(rows, "idx", "flip", "sum")
    return scanned.crossJoin(F.broadcast(at_start)).select("idx", (F.col("sum") + F.coalesce("start", F.lit(0))).cast("bigint").alias("viol"))  # one row


def best_prefix(gained: DataFrame, violations: DataFrame, prefix_tie: str = "longest", repair: bool = False) -> DataFrame:
    """One row (cut, total): the prefix of most gain that ends valid; cut = 0 if none gains.

    repair admits a prefix without gain, to leave an invalid start."""
    total = global_scan(gained.select("idx", "seq_gain"), "idx", "seq_gain", "total")
    order = F.col("idx") if prefix_tie == "longest" else -F.col("idx")
    valid = total.join(violations, "idx").filter("viol = 0")
    if not repair:
        valid = valid.filter("total > 0")
    best = valid.agg(F.max(F.struct("total", order.alias("o"))).alias("b"))
    return best.select(F.coalesce(F.abs("b.o"), F.lit(0)).cast("bigint").alias("cut"), F.coalesce("b.total", F.lit(0)).cast("bigint").alias("total"))


def apply_moves(assign: DataFrame, seq: DataFrame, cut: int) -> DataFrame:
    made = seq.filter(F.col("idx") <= cut).select("n", "pd")
    return assign.join(made, "n", "left").select("n", F.coalesce("pd", "p").alias("p"))


def project(assign: DataFrame, gamma: DataFrame) -> DataFrame:
    """Partitions of fine nodes from those of their coarse nodes."""
    return gamma.join(assign.withColumnRenamed("n", "c"), "c").select("n", "p")
