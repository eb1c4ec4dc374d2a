"""A hand-size hypergraph with known answers at every step."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from hgpart.model import Hypergraph, Limits
from hgpart.operators import candidates, contract, local, matching, metrics, moves, multilevel, sequence

EDGES = [(0, [0], [1, 2], 3), (1, [1], [0, 3], 2), (2, [2], [3, 4], 2), (3, [4], [5, 6], 4), (4, [6], [4, 7], 1), (5, [7], [5], 2), (6, [3], [2, 7], 1), (7, [5], [4, 5, 6], 1)]
LIMITS = Limits(4, 6)
HIST = {(0, 1): 5, (0, 2): 3, (0, 3): 2, (1, 2): 3, (1, 3): 2, (2, 3): 3, (2, 4): 2, (2, 7): 1, (3, 4): 2, (3, 7): 1, (4, 5): 5, (4, 6): 6, (4, 7): 1, (5, 6): 5, (5, 7): 2, (6, 7): 1}


@pytest.fixture(scope="module")
def hg(spark):
    pins = {(e, n, n in s, n in d) for e, s, d, _ in EDGES for n in s + d}
    rows = spark.createDataFrame(sorted(pins), "e long, n long, is_src boolean, is_dst boolean")
    return Hypergraph.from_pins(rows, spark.createDataFrame([(e, w) for e, _, _, w in EDGES], "e long, w long"))


def local_graph():
    pins = sorted({(e, n, n in s, n in d) for e, s, d, _ in EDGES for n in s + d})
    e, n, s, d = map(np.array, zip(*pins))
    return local.Graph(e, n, s, d, np.array([w for *_, w in EDGES]), np.ones(8, np.int64), np.ones(8, np.int64))


def assigned(spark, parts):
    return spark.createDataFrame(list(enumerate(parts)), "n long, p long")


def test_histogram(hg):
    assert {(r.n, r.m): r.hist for r in candidates.connection_histogram(hg).collect()} == HIST


def test_proposals_and_matching(hg):
    p = candidates.propose_candidates(hg, LIMITS)
    assert {r.n: (r.cand, r.score) for r in p.collect()} == {0: (1, 5), 1: (0, 5), 2: (3, 3), 3: (2, 3), 4: (6, 6), 5: (6, 5), 6: (4, 6), 7: (5, 2)}
    assert {r.cand: r.n for r in matching.winners(p).collect()} == {0: 1, 1: 0, 2: 3, 3: 2, 4: 6, 6: 4, 5: 7}
    for method in ("doubling", "levels"):
        assert {(r.n, r.mate) for r in matching.match_pairs(p, method).collect()} == {(0, 1), (1, 0), (2, 3), (3, 2), (4, 6), (6, 4), (5, 7), (7, 5)}
    assert {r.n_rows for r in matching.check_matching(p, matching.match_pairs(p)).collect()} == {0}


def test_variants_propose_alike(hg):
    same = sorted(candidates.propose_candidates(hg, LIMITS).collect())
    assert sorted(candidates.propose_batched(hg, LIMITS, 3).collect()) == same
    assert sorted(candidates.propose_deferred(hg, LIMITS, 1).collect()) == same


def test_coarsening_reaches_the_optimum(spark, hg):
    levels = multilevel.coarsen(hg, LIMITS)
    found = {r.n: r.p for r in multilevel.initial_assignment(levels).collect()}
    assert found == {0: 0, 1: 0, 2: 0, 3: 0, 4: 4, 5: 4, 6: 4, 7: 4}
    row = metrics.summary(hg, multilevel.initial_assignment(levels), LIMITS).first()
    assert (row.connectivity, row.n_parts, row.n_broken, row.max_inbound) == (3, 2, 0, 6)
    g = local_graph()
    best = min(
        local.connectivity(g, np.array(p))
        for p in itertools.product(range(3), repeat=8)
        if all(p.count(q) <= 4 and len({e for e, _, d, _ in EDGES if any(p[n] == q for n in d)}) <= 6 for q in range(3))
    )
    assert best == 3
    p, _ = local.multilevel(g, 4, 6)
    assert p.tolist() == [found[n] for n in range(8)]


REFINE = [
    ([0, 1, 2, 0, 1, 2, 0, 1], [(4, 1, 0, 7, 7, 0), (5, 2, 1, 7, 2, 0), (2, 2, 1, 6, 4, 0), (6, 0, 1, 6, 0, 1), (1, 1, 0, 5, 2, 0), (0, 0, 1, 3, -2, 2), (3, 0, 1, 3, 1, 2), (7, 1, 2, 2, -4, 2)], 5, 15, (27, 12)),
    ([0, 0, 0, 1, 1, 1, 2, 2], [(6, 2, 1, 5, 5, 0), (3, 1, 0, 3, 3, 0), (7, 2, 1, 3, 3, 0), (5, 1, 2, 2, -7, 0)], 3, 11, (14, 3)),
]


@pytest.mark.parametrize("start, rows, cut, total, conn", REFINE)
def test_refinement(spark, hg, start, rows, cut, total, conn):
    a = assigned(spark, start)
    pe = moves.partition_pins(hg, a)
    seq = sequence.sequence_moves(moves.propose_moves(hg, a, pe, LIMITS))
    loads = moves.partition_loads(hg, a, pe)
    for method in ("scan", "pairs"):
        gained = sequence.sequence_gains(hg, seq, pe, method)
        assert [(r.n, r.ps, r.pd, r.gain, r.seq_gain) for r in gained.orderBy("idx").collect()] == [r[:5] for r in rows]
    flips = sequence.validity_flips(sequence.size_events(hg, seq), sequence.inbound_transitions(sequence.inbound_events(hg, seq), pe), loads, LIMITS)
    viol = sequence.active_violations(seq, flips, loads, LIMITS)
    assert [r.viol for r in viol.orderBy("idx").collect()] == [r[5] for r in rows]
    assert tuple(sequence.best_prefix(gained, viol).first()) == (cut, total)
    assert metrics.connectivity(hg, a).first()[0] == conn[0]
    assert metrics.connectivity(hg, sequence.apply_moves(a, seq, cut)).first()[0] == conn[1]
    p, top, made = local.refine_pass(local_graph(), np.array(start), np.ones(8, bool), 4, 6)
    assert (top, made, local.connectivity(local_graph(), p)) == (total, cut, conn[1])


def test_prefix_ties(spark, hg):
    start = [0, 1, 0, 1, 2, 2, 0, 1]
    a = assigned(spark, start)
    assert multilevel.refine_once(hg, a, LIMITS)[1:] == (9, 3)
    assert multilevel.refine_once(hg, a, LIMITS, prefix_tie="shortest")[1:] == (9, 2)


def test_contraction_keeps_connectivity(spark, hg):
    p = candidates.propose_candidates(hg, LIMITS)
    gamma = contract.coarse_map(hg.nodes, matching.match_pairs(p))
    coarse = contract.contract(hg, gamma)
    a = assigned(spark, [0, 0, 1, 1, 2, 3, 2, 3])
    up = gamma.join(a, "n").select(F.col("c").alias("n"), "p").distinct()
    assert metrics.connectivity(coarse, up).first() == metrics.connectivity(hg, a).first()
    assert {r.n: r.size for r in coarse.nodes.collect()} == {0: 2, 2: 2, 4: 2, 5: 2}
