"""Disjoint pairs from the proposals: every node proposes once, so the proposal graph is a pseudo-forest
whose cycles, thanks to the tie-break by id, all have length two.

M(n), "n is matched with its candidate", holds for two-cycles and for a node that won its candidate's slot while
that candidate is not matched with its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.model import argmax_by
from hgpart.plans.checkpoints import materialize


def two_cycles(proposal: DataFrame) -> DataFrame:
    """(n, mate): nodes whose candidate proposes them."""
    back = proposal.select(F.col("n").alias("cand"), F.col("cand").alias("n"))
    return proposal.select("n", "cand").join(back, ["n", "cand"], "left_semi").select("n", F.col("cand").alias("mate"))


def winners(proposal: DataFrame) -> DataFrame:
    """(cand, score, n): the best proposer of each candidate, the larger id on ties."""
    return argmax_by(proposal, "cand", "score", "n").select("cand", "score", "n")


def _state(proposal: DataFrame) -> DataFrame:
    """(n, cand, tgt, odd, val): val is known for two-cycles (true) and losers (false)."""
    roots = two_cycles(proposal).select("n", F.lit(True).alias("root"))
    won = winners(proposal).select("n", F.lit(True).alias("won"))
    value = F.when(F.col("root"), True).when(F.col("won").isNull(), False)
    return proposal.join(roots, "n", "left").join(won, "n", "left").select("n", "cand", F.col("cand").alias("tgt"), F.lit(True).alias("odd"), value.alias("val"))


def match_pairs(proposal: DataFrame, method: str = "doubling") -> DataFrame:
    """(n, mate) both ways for every matched pair.

    "doubling" jumps twice as far each round: rounds grow with the logarithm of the longest run of winners;
    "levels" resolves one step a round. One count a round reaches the driver."""
    if method not in ("doubling", "levels"):
        raise ValueError(method)
    state = materialize(_state(proposal), "match")
    while not state.filter("val is null").isEmpty():
        ahead = state.select(F.col("n").alias("tgt"), F.col("tgt").alias("tgt2"), F.col("odd").alias("odd2"), F.col("val").alias("val2"))
        joined = state.filter("val is null").join(ahead, "tgt")
        flip = lambda a, b: a != b
        if method == "doubling":
            moved = joined.select(
                "n", "cand", F.when(F.col("val2").isNull(), F.col("tgt2")).otherwise(F.col("tgt")).alias("tgt"),
                F.when(F.col("val2").isNull(), flip(F.col("odd"), F.col("odd2"))).otherwise(F.col("odd")).alias("odd"),
                F.when(F.col("val2").isNotNull(), flip(F.col("val2"), F.col("odd"))).alias("val"),
            )
        else:
            moved = joined.select("n", "cand", "tgt", "odd", F.when(F.col("val2").isNotNull(), ~F.col("val2")).alias("val"))
        state = materialize(state.filter("val is not null").unionByName(moved), "match")
    pair = state.filter("val").select(F.least("n", "cand").alias("a"), F.greatest("n", "cand").alias("b")).distinct()
    return pair.select(F.explode(F.array(F.struct(F.col("a").alias("n"), F.col("b").alias("mate")), F.struct(F.col("b").alias("n"), F.col("a").alias("mate")))).alias("x")).select("x.*")


def match_exact(proposal: DataFrame) -> DataFrame:
    """(n, mate): a matching of the largest total score in the proposal graph, by dynamic programming.

    With a two-cycle taken as one edge each component is a tree. Leaves are folded in round by round: a node is
    ready when all its proposers are. best is the largest weight in a node's subtree, free the same with
    the node unmatched. A walk from the roots down then settles who is matched."""
    roots = two_cycles(proposal)
    up = proposal.join(roots.select("n", F.lit(True).alias("root")), "n", "left").select("n", "cand", "score", F.coalesce("root", F.lit(False)).alias("root"))
    # nodes that only receive nothing are leaves; parents: everyone's candidate unless in a two-cycle
    tree = materialize(up.select("n", "score", F.when(~F.col("root"), F.col("cand")).alias("parent"), F.when(F.col("root"), F.col("cand")).alias("twin")), "tree")
    kids = tree.filter("parent is not null").groupBy("parent").agg(F.count(F.lit(1)).alias("k")).withColumnRenamed("parent", "n")
    todo = materialize(tree.join(kids, "n", "left").select("n", "parent", "twin", "score", F.coalesce("k", F.lit(0)).alias("k")), "todo")
    done = None
    while True:
        ready_kids = None if done is None else done.filter("parent is not null").groupBy(F.col("parent").alias("n")).agg(
            F.count(F.lit(1)).alias("got"), F.sum("best").alias("sum_best"), F.max(F.struct((F.col("free") - F.col("best") + F.col("score")).alias("lift"), F.col("n").alias("who"))).alias("lift")
        )
        if done is None:
            ready = todo.filter("k = 0").select("n", "parent", "twin", "score", F.lit(0).cast("bigint").alias("free"), F.lit(0).cast("bigint").alias("best"), F.lit(None).cast("bigint").alias("who"))
        else:
            ready = (
                todo.join(done.select("n"), "n", "left_anti").join(ready_kids, "n").filter("k = got")
                .select("n", "parent", "twin", "score", F.col("sum_best").alias("free"), F.expr("sum_best + greatest(lift.lift, 0)").alias("best"), F.expr("CASE WHEN lift.lift > 0 THEN lift.who END").alias("who"))
            )
        ready = materialize(ready, "ready")
        if ready.isEmpty():
            break
        done = ready if done is None else materialize(done.unionByName(ready), "done")
    if done is None:
        return proposal.select("n", F.col("cand").alias("mate"))
    # settle: at a two-cycle the edge is used if that beats the two sides alone
    twin = done.select(F.col("n").alias("twin"), F.col("free").alias("free2"), F.col("best").alias("best2"))
    rooted = done.filter("twin is not null").join(twin, "twin")
    settled = materialize(rooted.select("n", F.when(F.expr("free + free2 + score > best + best2"), F.col("twin")).otherwise(F.col("who")).alias("mate"), "who"), "settled").select("n", "mate")
    settled = materialize(settled, "settled")
    frontier = settled
    while not frontier.isEmpty():
        above = frontier.select(F.col("n").alias("parent"), F.col("mate").alias("above"))
        below = done.filter("parent is not null").join(above, "parent")
        frontier = materialize(below.select("n", F.when(F.expr("above <=> n"), F.col("parent")).otherwise(F.col("who")).alias("mate")), "frontier")
        settled = settled.unionByName(frontier)
    pairs = settled.filter("mate is not null").select(F.least("n", "mate").alias("a"), F.greatest("n", "mate").alias("b")).distinct()
    return pairs.select(F.explode(F.array(F.struct(F.col("a").alias("n"), F.col("b").alias("mate")), F.struct(F.col("b").alias("n"), F.col("a").alias("mate")))).alias("x")).select("x.*")


def check_matching(proposal: DataFrame, matched: DataFrame) -> DataFrame:
    """(rule, n_rows): scores that fall towards the root, cycles longer than two, mates that are not mutual, nodes matched twice."""
    ahead = proposal.select(F.col("n").alias("cand"), F.col("cand").alias("next"), F.col("score").alias("next_score"))
    steps = proposal.join(ahead, "cand")
    falling = steps.filter("next_score < score")
    # on a longer cycle scores are constant; such a node's candidate's candidate is someone else with equal score and a larger id than its own
    odd = steps.filter("next <> n AND next_score = score AND next < n")
    back = matched.select(F.col("mate").alias("n"), F.col("n").alias("mate"))
    rules = [("falling_scores", falling), ("long_cycles", odd), ("not_mutual", matched.join(back, ["n", "mate"], "left_anti")), ("matched_twice", matched.groupBy("n").count().filter("count > 1"))]
    out = None
    for name, rows in rules:
        one = rows.agg(F.count(F.lit(1)).alias("n_rows")).select(F.lit(name).alias("rule"), "n_rows")
        out = one if out is None else out.unionByName(one)
    return out


def matching_weight(proposal: DataFrame, matched: DataFrame) -> DataFrame:
    """One row: pairs and their total score."""
    scored = matched.join(proposal.select("n", F.col("cand").alias("mate"), "score"), ["n", "mate"], "left").groupBy(F.least("n", "mate").alias("a"), F.greatest("n", "mate").alias("b")).agg(F.max("score").alias("score"))
    return scored.agg(F.count(F.lit(1)).alias("n_pairs"), F.coalesce(F.sum("score"), F.lit(0)).alias("weight"))
