"""Engine against its local twin, brute force, and awkward inputs."""

import inspect
import itertools
import random
import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from hgpart import catalog, model
from hgpart.model import Hypergraph, Limits
from hgpart.operators import blocks, candidates, local, matching, metrics, moves, multilevel
from hgpart.sources.builders import BUILDERS, limits_of

SF = "/root/testdata/sf0.001"


def random_graph(spark, seed, n=14, e=16):
    r = random.Random(seed)
    rows, weights = [], []
    for k in range(e):
        nodes = r.sample(range(n), r.randrange(1, 6))
        rows += [(k, m, i == 0, i > 0 or len(nodes) == 1) for i, m in enumerate(nodes)]
        weights.append((k, r.randrange(0, 4)))
    return Hypergraph.from_pins(spark.createDataFrame(rows, "e long, n long, is_src boolean, is_dst boolean"), spark.createDataFrame(weights, "e long, w long"), spark.range(n).select(F.col("id").alias("n")))


@pytest.mark.parametrize("seed, limits", [(1, Limits(4, 9)), (2, Limits(3, 100)), (3, Limits(5, 7, "incident")), (4, Limits(6, 5, "out"))])
def test_distributed_equals_local(spark, seed, limits):
    hg = random_graph(spark, seed)
    lim = limits
    near = multilevel.HypergraphPartitioner(lim).fit(hg).assign
    far = multilevel.HypergraphPartitioner(lim, local_pins=-1).fit(hg).assign
    assert sorted(near.collect()) == sorted(far.collect())
    start = {r.n: 1 for r in hg.nodes.collect()}
    assert {r.n for r in near.collect()} == set(start)


def test_exact_matching_by_brute_force(spark):
    for seed in range(4):
        r = random.Random(seed)
        n = 9
        # proposals as the engine makes them: symmetric scores, largest (score, id) wins
        score = {frozenset(p): r.randrange(1, 5) for p in itertools.combinations(range(n), 2) if r.random() < 0.4}
        rows = []
        for v in range(n):
            best = max(((s, next(iter(p - {v}))) for p, s in score.items() if v in p), default=None)
            if best:
                rows.append((v, best[1], best[0]))
        p = spark.createDataFrame(rows, "n long, cand long, score long")
        edges = {frozenset((a, b)): s for a, b, s in rows}
        best = max(sum(edges[x] for x in c) for k in range(len(edges) + 1) for c in itertools.combinations(edges, k) if len(set().union(*c)) == 2 * len(c))
        exact = matching.matching_weight(p, matching.match_exact(p)).first().weight
        two = matching.matching_weight(p, matching.match_pairs(p)).first().weight
        assert exact == best and 2 * two >= exact
        assert sorted(matching.match_pairs(p, "levels").collect()) == sorted(matching.match_pairs(p).collect())


def test_result_is_valid_on_every_workload(spark):
    for name in ("basket", "terms", "links", "knn"):
        hg = BUILDERS[name](spark, SF)
        lim = limits_of(name, hg)
        row = metrics.summary(hg, multilevel.HypergraphPartitioner(lim).fit(hg).assign, lim).first()
        assert row.n_broken == 0 and row.max_size <= lim.max_nodes


def test_methods_rank_as_published_on_clustered_data(spark):
    for name in ("terms", "links", "knn"):
        hg = BUILDERS[name](spark, SF)
        lim = limits_of(name, hg)
        conn = {}
        for method in ("multilevel", "overlap", "one_pass"):
            a = multilevel.run_local(hg, lim, method).filter("kind = 'assign'").select(F.col("a").alias("n"), F.col("b").alias("p"))
            conn[method] = metrics.connectivity(hg, a).first()[0]
        assert conn["multilevel"] <= conn["overlap"] <= conn["one_pass"]


def test_exhaustive_optimum_bounds_the_heuristics(spark):
    hg = BUILDERS["suppliers"](spark, SF)
    lim = Limits(4, 214)
    pins = [(r.e, r.n) for r in hg.pins.collect()]
    w = {r.e: r.w for r in hg.edges.collect()}
    a = multilevel.HypergraphPartitioner(lim).fit(hg).assign
    own = metrics.connectivity(hg, a).first()[0]
    by_edge = {}
    for e, n in pins:
        by_edge.setdefault(e, []).append(n)
    masks = {n: {e for e, m in pins if m == n} for n in range(10)}

    def parts(k):  # restricted growth strings with at most 4 a part
        def go(p, m):
            if len(p) == 10:
                yield p
                return
            for q in range(m + 1):
                if p.count(q) < 4:
                    yield from go([*p, q], max(m, q + 1))
        return go([], 0)

    best, tried = None, 0
    arr = np.array([[n in by_edge[e] for n in range(10)] for e in sorted(by_edge)])
    weight = np.array([w[e] for e in sorted(by_edge)])
    for p in parts(10):
        if max(p) > 3:
            continue
        groups = [[n for n in range(10) if p[n] == q] for q in range(max(p) + 1)]
        if any(len(set().union(*(masks[n] for n in g))) > 214 for g in groups):
            continue
        c = int((weight * (sum(arr[:, g].any(axis=1).astype(int) for g in groups) - 1)).sum())
        best = c if best is None else min(best, c)
    assert best is not None and own >= best


def test_levels_are_reported_beyond_one_task(spark, monkeypatch):
    hg, lim = random_graph(spark, 4), Limits(4, 100)
    near = sorted(catalog._levels(hg, lim).collect())
    monkeypatch.setattr(multilevel, "fits_locally", lambda *_: False)
    monkeypatch.setattr(multilevel, "run_local", None)
    assert sorted(catalog._levels(hg, lim).collect()) == near


def test_comparison_has_all_workloads_and_means(spark):
    assert catalog.compare.__defaults__[0] == tuple(BUILDERS)
    rows = catalog.compare(spark, SF, ("links", "knn")).collect()
    for method in ("multilevel", "sequential", "overlap", "one_pass"):
        ratios = [r.ratio for r in rows if r.method == method]
        means = {(round(r.geometric, 9), round(r.arithmetic, 9)) for r in rows if r.method == method}
        assert len(ratios) == 2 and means == {(round(float(np.prod(ratios)) ** 0.5, 9), round(sum(ratios) / 2, 9))}


def test_both_paths_end_alike(spark):
    """passes=0 refines until nothing moves on both paths, and neither limits the number of levels."""
    assert inspect.signature(multilevel.coarsen).parameters["max_levels"].default is None
    hg, lim = random_graph(spark, 2), Limits(3, 100)
    near, far = (multilevel.HypergraphPartitioner(lim, passes=0, local_pins=k).fit(hg).assign for k in (multilevel.LOCAL_PINS, -1))
    assert sorted(near.collect()) == sorted(far.collect())
    level = [multilevel.Level(hg, None)]
    until, many = multilevel.refine(level, lim, 0), multilevel.refine(level, lim, 30)
    assert sorted(until.assign.collect()) == sorted(many.assign.collect()) and until.reports == many.reports and until.reports[0][-1] > 0


def test_sequential_refinement_reaches_a_fifth_target():
    """The four heaviest neighbours of node 0 lie in full partitions; the fifth has room."""
    homes = [[0], [1, 2, 3], [4, 5, 6], [7, 8, 9], [10, 11, 12], [13, 14]]
    edges = [(h, 100) for h in homes[1:]] + [([0, h[0]], 9 - k) for k, h in enumerate(homes[1:])]
    pins = [(e, n) for e, (held, _) in enumerate(edges) for n in held]
    p = np.array([h[0] for h in homes for _ in h])
    e, n = (np.array(x) for x in zip(*pins))
    g = local.Graph(e, n, np.zeros(len(e), bool), np.ones(len(e), bool), np.array([w for _, w in edges]), np.ones(len(edges), np.int64), np.ones(15, np.int64))
    out = local._sequential_refine(g, p, np.ones(15, bool), 3, 100)
    assert out.tolist() == [13, *p.tolist()[1:]]


@pytest.mark.parametrize("seed", range(30))
def test_sequential_refinement_takes_the_best_move(seed):
    """Against a search that counts connectivity anew for every move; hyperedges of many and of few nodes."""
    r = random.Random(seed)
    n_nodes, n_edges = r.randrange(4, 12), r.randrange(3, 12)
    pins = [(e, n) for e in range(n_edges) for n in r.sample(range(n_nodes), r.randrange(2, n_nodes + 1))]
    e, n = (np.array(x) for x in zip(*pins))
    dst = np.array([r.random() < 0.7 for _ in pins])
    g = local.Graph(e, n, ~dst, dst, np.array([1 + 7 * k % 5 for k in range(n_edges)]), np.ones(n_edges, np.int64), np.ones(n_nodes, np.int64))
    first = np.array([r.randrange(4) for _ in range(n_nodes)])
    most, inbound = max(r.randrange(3, 6), int(np.bincount(first).max())), r.randrange(5, 14)
    p, locked, log, total, best, at = first.copy(), set(), [], 0, 0, 0
    while True:
        moves = []
        for v in set(range(n_nodes)) - locked:
            near = {int(p[m]) for x in e[n == v] for m in n[e == x]} - {int(p[v])}
            for q in near:
                to = p.copy()
                to[v] = q
                if (to == q).sum() <= most and len(set(e[dst & (to[n] == q)].tolist())) <= inbound:
                    moves.append((local.connectivity(g, p) - local.connectivity(g, to), -v, q))
        if not moves:
            break
        gain, v, q = max(moves)
        log.append((-v, int(p[-v])))
        p[-v] = q
        locked.add(-v)
        total += gain
        if total > best:
            best, at = total, len(log)
    for v, q in reversed(log[at:]):
        p[v] = q
    assert local._sequential_refine(g, first, np.ones(n_nodes, bool), most, inbound).tolist() == p.tolist()


@pytest.mark.parametrize("rows, n_nodes", [([], 3), ([(0, 0)], 1), ([(0, 0), (0, 0), (0, 1)], 2)])
def test_small_inputs(spark, rows, n_nodes):
    hg = Hypergraph.from_pins(spark.createDataFrame(rows, "e long, n long"), None, spark.range(n_nodes).select(F.col("id").alias("n")))
    for lim in (Limits(1, 5), Limits(10, 10)):
        for far in (multilevel.LOCAL_PINS, -1):
            a = multilevel.HypergraphPartitioner(lim, local_pins=far).fit(hg).assign.collect()
            assert len(a) == n_nodes
            if lim.max_nodes == 1:
                assert len({r.p for r in a}) == n_nodes


def test_validate_reports(spark):
    pins = spark.createDataFrame([(0, 0, False, True), (0, 0, False, True), (1, 9, False, True), (7, 0, False, True)], "e long, n long, is_src boolean, is_dst boolean")
    edges = spark.createDataFrame([(0, -1, 1), (1, 2, 1)], "e long, w long, mult int")
    nodes = spark.createDataFrame([(0, 5)], "n long, size long")
    found = {r.problem: r.n_rows for r in model.validate(Hypergraph(pins, edges, nodes), Limits(4, 1)).collect()}
    assert found == {"duplicate_pins": 1, "negative_weights": 1, "pins_without_edge": 1, "pins_without_node": 1, "oversized_nodes": 1, "overbound_nodes": 1}


def test_merging_parallel_edges_changes_nothing(spark):
    hg = BUILDERS["links"](spark, SF)
    merged = model.merge_parallel(hg)
    lim = limits_of("links", hg)
    key = lambda df: sorted(df.collect())
    assert key(candidates.propose_candidates(hg, lim)) == key(candidates.propose_candidates(merged, lim))


def test_same_under_other_partitioning(spark):
    hg = BUILDERS["basket"](spark, SF)
    lim = limits_of("basket", hg)
    first = sorted(candidates.propose_candidates(hg, lim).collect())
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        again = sorted(candidates.propose_candidates(Hypergraph(hg.pins.repartition(5), hg.edges, hg.nodes), lim).collect())
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")
        spark.conf.set("spark.sql.adaptive.enabled", "true")
    assert first == again


def test_plans(spark):
    hg = random_graph(spark, 1)
    plan = candidates.propose_candidates(hg, Limits(16, 100))._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan and "SortAggregate" not in plan.split("== Physical Plan ==")[1]
    scan = spark.read.parquet(f"{SF}/lineitem.parquet").filter("l_quantity > 45").select("l_orderkey")._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in scan


def test_switch_between_levels(spark):
    """The finer levels run distributed, the coarser ones in one task, and nothing shows it."""
    hg, lim = random_graph(spark, 5, 40, 44), Limits(7, 30)
    near = multilevel.HypergraphPartitioner(lim).fit(hg)
    sizes = [r[2] for r in sorted(near.reports)]
    pins = (sizes[0] + sizes[-1]) // 2
    assert sizes[0] > pins >= sizes[-1]
    mixed = multilevel.HypergraphPartitioner(lim, local_pins=pins).fit(hg)
    assert sorted(near.assign.collect()) == sorted(mixed.assign.collect()) and sorted(near.reports) == sorted(mixed.reports)


def test_options_are_honoured(spark, monkeypatch):
    """Neighbours in memory and deferred checks leave the one-task path, and do not change the result; neither do blocks of events."""
    hg, lim = random_graph(spark, 3), Limits(5, 20)
    bare = {"refine": False, "max_levels": 2}
    near = sorted(multilevel.HypergraphPartitioner(lim, **bare).fit(hg).assign.collect())
    monkeypatch.setattr(multilevel, "run_local", None)
    for opts in ({"materialize_neighbors": True}, {"deferred": 2}):
        assert sorted(multilevel.HypergraphPartitioner(lim, **bare, **opts).fit(hg).assign.collect()) == near
    start = catalog.modulo(hg, 4)
    whole, blocked = (multilevel.refine_once(hg, start, lim, event_block=k) for k in (multilevel.EVENT_BLOCK, 2))
    assert whole[1:] == blocked[1:] and whole[2] > 0 and sorted(whole[0].collect()) == sorted(blocked[0].collect())


def test_cells_make_every_pair_once(spark, chunk=2):
    hg, lim = random_graph(spark, 8, 12, 30), Limits(4, 9)
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(candidates.co_pins(hg, lim, chunk)) == key(candidates.co_pins(hg, lim))
    assert key(model.neighbors(hg, chunk)) == key(model.neighbors(hg))
    merged = model.merge_parallel(hg)
    for g in (hg, merged):
        want = key(candidates.propose_candidates(g, lim))
        assert key(candidates.propose_candidates(g, lim, chunk=chunk, bounds=(1000, 20))) == want
        assert key(candidates.propose_deferred(g, lim, 1)) == want == key(candidates.propose_deferred(g, lim, 2, chunk))


@pytest.mark.parametrize("seed", range(12))
def test_overlap_by_brute_force(seed):
    r = random.Random(seed)
    n_nodes, n_edges = r.randrange(3, 14), r.randrange(2, 14)
    pins = [(e, n) for e in range(n_edges) for n in r.sample(range(n_nodes), r.randrange(1, n_nodes + 1))]
    e, n = (np.array(x) for x in zip(*pins))
    dst, w = np.array([r.random() < 0.6 for _ in pins]), np.array([r.randrange(4) for _ in range(n_edges)])
    g = local.Graph(e, n, ~dst, dst, w, np.ones(n_edges, np.int64), np.ones(n_nodes, np.int64))
    most, inbound = r.randrange(2, 5), r.randrange(3, 9)
    parts: dict[int, list[int]] = {}
    for v in range(n_nodes):
        best = None
        for q, held in parts.items():
            shared = {x for x, m in pins if m == v} & {x for x, m in pins if m in held}
            bound = {x for (x, m), d in zip(pins, dst) if d and m in (*held, v)}
            if shared and len(held) < most and len(bound) <= inbound:
                best = max(best or (-1, -1), (int(w[list(shared)].sum()), q))
        parts.setdefault(best[1] if best else v, []).append(v)
    want = {v: q for q, held in parts.items() for v in held}
    assert local.overlap(g, most, inbound).tolist() == [want[v] for v in range(n_nodes)]


def test_baselines_are_valid(spark):
    for name in ("suppliers", "dialog", "links", "cohort", "trade"):
        hg = BUILDERS[name](spark, SF)
        lim = limits_of(name, hg)
        for method, opts in (("sequential", {}), ("overlap", {}), ("overlap", {"fallback": "newest"}), ("one_pass", {})):
            a = multilevel.run_local(hg, lim, method, **opts).select(F.col("a").alias("n"), F.col("b").alias("p"))
            row = metrics.summary(hg, a, lim).first()
            assert row.n_broken == 0 and row.max_size <= lim.max_nodes, (name, method)


def test_ablations(spark):
    q = catalog.queries()
    whole = q["wl_terms_summary"](spark, SF).first()
    bare = q["ablate_no_refinement"](spark, SF).first()
    assert whole.connectivity <= bare.connectivity and whole.n_broken == bare.n_broken == 0
    for name in ("ablate_no_inbound_limit", "ablate_no_size_limit"):
        row = q[name](spark, SF).first()
        assert row.n_broken == 0 and row.connectivity >= 0
    assert q["ablate_merged_edges"](spark, SF).first().connectivity == q["wl_links_summary"](spark, SF).first().connectivity


def test_rematching_adds_pairs(spark):
    hg, lim = random_graph(spark, 9, 20, 24), Limits(4, 30)
    once = candidates.propose_candidates(hg, lim)
    first = {tuple(x) for x in matching.match_pairs(once).collect()}
    again = {tuple(x) for x in catalog._rematch(hg, lim, 3).collect()}
    assert first <= again and len({n for n, _ in again}) == len(again) and {(m, n) for n, m in again} == again


def test_nearest_in_blocks(spark):
    from hgpart.sources.builders import nearest

    vectors = spark.read.parquet(f"{SF}/embeddings.parquet").limit(120)
    assert sorted(nearest(vectors, 5, 16).collect()) == sorted(nearest(vectors, 5).collect())


def test_streams_without_sql(spark):
    from hgpart.streaming import streams

    placed = streams.stream_one_pass(spark, SF, most=4, shards=3).collect()
    users = {r.user_id for r in spark.read.parquet(f"{SF}/events.parquet").select("user_id").distinct().collect()}
    assert sorted(r.n for r in placed) == sorted(users)
    held = {}
    for r in placed:
        held.setdefault(r.p, []).append(r.n)
    assert all(len(x) <= 4 and {n % 3 for n in x} == {p % 3} for p, x in held.items())
    by_day = {r.start: r.n for r in spark.sql(f"SELECT date_trunc('day', ts) AS start, count(*) AS n FROM parquet.`{SF}/events.parquet` GROUP BY 1").collect()}
    late = {r.start: r.n_events for r in streams.stream_late(spark, SF).collect()}
    assert late and late.keys() <= by_day.keys() and all(n <= by_day[k] for k, n in late.items()) and sum(late.values()) < sum(by_day.values())


def test_sketches_are_near(spark):
    rows = catalog.queries()["approx_union_size"](spark, "/root/testdata/sf0.01").collect()
    assert rows and all(abs(r.estimate - r.exact) <= 0.1 * r.exact + 2 and abs(r.approx - r.exact) <= 0.2 * r.exact + 2 for r in rows)


def test_a_cluster_needs_a_shared_folder(spark, monkeypatch):
    from hgpart.plans import checkpoints

    class Context:
        master = "spark://host:7077"

        def getConf(self):
            return {}

    class Session:
        sparkContext = Context()

    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        checkpoints.shared_folder(Session())


def test_level_costs(spark):
    hg, lim = random_graph(spark, 6), Limits(4, 30)
    rows = multilevel.level_costs(hg, lim, 1).collect()
    assert len(rows) == 1 and rows[0].n_nodes == 14 and rows[0].jobs > 3 and rows[0].tasks >= rows[0].stages > 3 and rows[0].seconds > 0


def small_and_large_edges(spark):
    """A hypergraph of 60 nodes with edges of 1 to 40 pins, and its pins (e, n, is_src, is_dst) and weights as arrays."""
    rng = np.random.default_rng(5)
    sizes = [1, 2, 3, 40, 25, *rng.integers(2, 9, 30)]
    rows = [(e, int(n), bool(rng.integers(2)), bool(rng.integers(2))) for e, s in enumerate(sizes) for n in rng.choice(60, s, replace=False)]
    weights = [(e, int(rng.integers(1, 9))) for e in range(len(sizes))]
    hg = Hypergraph.from_pins(spark.createDataFrame(rows, "e long, n long, is_src boolean, is_dst boolean"), spark.createDataFrame(weights, "e long, w long"), spark.range(60).select(F.col("id").alias("n")))
    return hg, [np.array(x) for x in zip(*sorted(tuple(r) for r in hg.pins.select("e", "n", "is_src", "is_dst").collect()))], np.array([w for _, w in weights])


@pytest.mark.parametrize("wide, at_once", [(4, 64), (1 << 20, 1)])
def test_proposals_by_blocks(spark, monkeypatch, wide, at_once):
    """Small and large hyperedges, tables and lists of pairs, blocks of one node and of all."""
    monkeypatch.setattr(blocks, "WIDE", wide)
    monkeypatch.setattr(blocks, "PAIRS_AT_ONCE", at_once)
    hg, (e, n, src, dst), w = small_and_large_edges(spark)
    for bound, most, work in (("in", 7, 1), ("incident", 9, 1 << 20)):
        g = local.Graph(e, n, src, dst, w, np.ones_like(w), np.ones(60, np.int64), bound)
        cand, score = local.proposals(g, 2, most)
        got = candidates.propose_by_blocks(hg, Limits(2, most, bound), least=work, most=work)
        assert {(r.n, r.cand, r.score) for r in got.collect()} == {(k, int(cand[k]), int(score[k])) for k in range(60) if cand[k] >= 0}


@pytest.mark.parametrize("admit", ["not_full", "fits"])
def test_moves_by_blocks(spark, monkeypatch, admit, most=9):
    """By brute force, with partitions that are full, so that some hyperedges have no partition to move to."""
    monkeypatch.setattr(blocks, "WIDE", 4)
    hg, (e, n, _, _), w = small_and_large_edges(spark)
    size = lambda q: 8 + (q < 4)
    want = {}
    for v in range(60):
        held = [(int(w[k]), {int(x) % 7 for x in n[e == k]}, {int(x) % 7 for x in n[e == k] if x != v}) for k in e[n == v]]
        gain = {q: sum(x * ((v % 7 not in rest) - (q not in all_)) for x, all_, rest in held) for q in range(7) if q != v % 7}
        found = [(x, q) for q, x in gain.items() if x > 0 and (size(q) < most if admit == "not_full" else size(q) + 1 <= most)]
        if found:
            want[v] = (v, v % 7, max(found)[1], max(found)[0])
    assign = hg.nodes.select("n", F.pmod("n", F.lit(7)).alias("p"))
    got = moves.propose_moves(hg, assign, moves.partition_pins(hg, assign), Limits(most), admit)
    assert {r.n: tuple(r) for r in got.collect()} == want


def test_full_partitions_cost_a_local_round_nothing():
    """Pins meet only partitions that take a node: 3,000 pins and 750 full partitions make no table of pairs."""
    n = np.arange(3000)
    yes = np.ones(3000, bool)
    g = local.Graph(np.zeros(3000, np.int64), n, ~yes, yes, np.array([5]), np.array([1]), np.ones(3000, np.int64))
    tracemalloc.start()
    p, gained, made = local.refine_pass(g, n // 4 * 4, yes, 4, 100)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert (gained, made) == (0, 0) and (p == n // 4 * 4).all() and peak < 4_000_000


def test_packed_keys_sort_as_separate_ones():
    rng = np.random.default_rng(5)
    for top in (6, 1 << 21, 1 << 40):  # the last do not fit one key
        keys = [rng.integers(0, top, 500) // (top // 5) for _ in range(3)]
        keys[2] = keys[2] * (top // 5)
        order, starts = local._runs(*keys)
        assert (order == np.lexsort(keys[::-1])).all()
        rows = list(zip(*(k[order].tolist() for k in keys)))
        assert starts.tolist() == [k for k in range(500) if not k or rows[k] != rows[k - 1]]


@pytest.mark.parametrize("seed", range(40))
def test_levels_reuse_what_has_not_changed(seed, monkeypatch):
    """Candidates and targets handed from level to level are those that each level would find anew."""
    rng = np.random.default_rng(seed)
    n_nodes, n_edges = 50, 60
    keys = np.unique(rng.integers(0, n_nodes * n_edges, 160))
    e, n, dst = keys // n_nodes, keys % n_nodes, rng.random(len(keys)) < 0.7
    g = local.Graph(e, n, ~dst, dst, rng.integers(0, 5, n_edges), np.ones(n_edges, np.int64), rng.integers(1, 3, n_nodes))
    most, inbound, min_gain = 6, 12, 1 + seed % 2
    got = local.multilevel(g, most, inbound, min_gain=min_gain)[0]
    monkeypatch.setattr(local, "AT_ONCE", 7)
    monkeypatch.setattr(local, "KEPT_PINS", 0)
    assert (local.multilevel(g, most, inbound, min_gain=min_gain)[0] == got).all()
    levels = local.coarsen(g, np.ones(n_nodes, bool), most, inbound)
    p = np.arange(n_nodes)
    for k in range(len(levels) - 1, -1, -1):
        h, (_, live, gamma) = local.level_graph(levels, k), levels[k]
        if gamma is not None:
            mate = local.matching(*local.proposals(h, most, inbound))
            assert (gamma == np.minimum(mate, np.arange(n_nodes))).all()
            p = p[gamma]
        p = local.refine_pass(h, p, live, most, inbound, min_gain=min_gain)[0]
    assert (p == got).all()


def test_proposals_in_one_task_hold_few_pairs_at_once(monkeypatch):
    """4.5 million pairs of one hyperedge are never a table."""
    monkeypatch.setattr(local, "AT_ONCE", 100_000, raising=False)
    n, yes = np.arange(3000), np.ones(3000, bool)
    g = local.Graph(np.zeros(3000, np.int64), n, ~yes, yes, np.array([5]), np.array([1]), np.ones(3000, np.int64))
    tracemalloc.start()
    cand, score = local.proposals(g, 2, 100)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert cand.tolist() == [2999] * 2999 + [2998] and (score == 5).all() and peak < 30_000_000


@pytest.mark.parametrize("name", ["terms", "dialog"])
def test_texts_are_split_once(spark, name):
    assert "split(" not in BUILDERS[name](spark, SF).pins._jdf.queryExecution().toString()

@pytest.mark.parametrize("at_once", [3, 10_000])
def test_long_rows_of_joined_blocks(spark, monkeypatch, at_once):
    """Rows added up one by one, and blocks that are joined to share their columns."""
    monkeypatch.setattr(blocks, "LONG", 1)
    monkeypatch.setattr(blocks, "PAIRS_AT_ONCE", at_once)
    seen = []
    monkeypatch.setattr(blocks, "joined_bits", lambda *args: seen.append(1) or 2)
    hg = random_graph(spark, 5, 30, 40)
    hg = Hypergraph(hg.pins, hg.edges.withColumn("w", F.col("w") + 1), hg.nodes)
    for bound, most in (("in", 7), ("incident", 9)):
        lim = Limits(2, most, bound)
        valid = candidates.pair_valid(candidates.with_unions(candidates.connection_histogram(hg, lim), candidates.node_loads(hg, lim)), lim)
        want = model.argmax_by(candidates.mirrored(valid), "n", "score", "cand").select("n", "cand", "score")
        got = candidates.propose_by_blocks(hg, lim, least=9, most=9)
        assert sorted(got.collect()) == sorted(want.collect())
    assert len(seen) == 2


def test_blocks_are_joined_while_columns_fit(spark, monkeypatch):
    """Two large hyperedges that all nodes hold go to few tasks, and to one each if that is all that fits."""
    sizes = spark.range(2).select(F.col("id").alias("e"), F.lit(100).alias("s"))
    asked = spark.range(64).select(F.col("id").alias("at")).crossJoin(spark.range(2).select(F.col("id").alias("h")))
    assert blocks.joined_bits(asked, sizes, 1 << 40, 1 << 20) == 10
    monkeypatch.setattr(blocks, "JOINED_COLUMNS", 199)
    assert blocks.joined_bits(asked, sizes, 1 << 40, 1 << 20) == 0
    assert blocks.joined_bits(asked, sizes, 100, 50) == 0


def test_written_tables_are_kept_once(spark):
    hg = multilevel.kept(random_graph(spark, 1))
    assert multilevel.kept(hg).pins is hg.pins
    other = multilevel.kept(random_graph(spark, 1))
    multilevel.forget(other.pins)
    with pytest.raises(Exception):
        other.pins.count()
    assert hg.pins.count()


def test_small_tables_are_broadcast(spark, monkeypatch):
    """By rows once files are not tiny, and never if they are not written; sizes of a written hypergraph are counted once."""
    from hgpart.plans import checkpoints

    hinted = lambda df: "broadcast" in df._jdf.queryExecution().logical().toString().lower()
    df = checkpoints.materialize(spark.range(100))
    assert hinted(checkpoints.small(df)) and not hinted(checkpoints.small(spark.range(100)))
    monkeypatch.setattr(checkpoints, "SMALL_BYTES", 0)
    assert hinted(checkpoints.small(df))
    monkeypatch.setattr(checkpoints, "SMALL_ROWS", 99)
    assert not hinted(checkpoints.small(df))
    hg = multilevel.kept(random_graph(spark, 1))
    assert multilevel.volume(hg) is multilevel.volume(hg)


@pytest.mark.parametrize("seed, limits, opts", [(1, Limits(4, 9), {}), (3, Limits(5, 7, "incident"), {"admit": "fits", "passes": 2}), (5, Limits(6, 9, "out"), {"prefix_tie": "shortest", "max_levels": 2})])
def test_dealt_pins_end_alike(spark, monkeypatch, seed, limits, opts):
    """Pins dealt to chunks, and nodes to blocks, take the decisions of one task; levels that no task takes are dealt, not joined as tables."""
    hg = multilevel.kept(random_graph(spark, seed, 30, 50))
    near = multilevel.HypergraphPartitioner(limits, **opts).fit(hg)
    for name, small in (("CHUNK_PINS", 40), ("BLOCK_PINS", 20)):
        monkeypatch.setattr(multilevel.dealt, name, small)
    monkeypatch.setattr(multilevel, "coarsen", None)
    monkeypatch.setattr(multilevel, "run_local", None)
    far = multilevel.HypergraphPartitioner(limits, local_pins=-1, deal=True, **opts).fit(hg)
    assert sorted(near.assign.collect()) == sorted(far.assign.collect()) and sorted(near.reports) == sorted(far.reports)


def test_basket_meets_its_lines_once(spark, tmp_path):
    """One shuffle by order for all pins, whose first line is found there; lines of one part, or without an order or a part, are kept or left as before."""
    rows = [(1, 7, 2, 3.0), (1, 7, 1, 2.0), (1, 5, 3, 1.0), (1, 7, 4, 9.0), (2, 5, 1, 4.0), (2, None, 2, 1.0), (3, None, 1, 1.0), (3, 7, 2, 1.0), (None, 5, 1, 6.0)]
    spark.createDataFrame(rows, "l_orderkey long, l_partkey long, l_linenumber int, l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(5,), (7,)], "p_partkey long").write.parquet(f"{tmp_path}/part.parquet")
    hg = BUILDERS["basket"](spark, str(tmp_path))
    assert {tuple(r) for r in hg.pins.collect()} == {(1, 7, True, False), (1, 5, False, True), (2, 5, True, False), (2, None, False, True), (3, None, False, True), (3, 7, False, True)}
    assert hg.pins.count() == 6 and {tuple(r) for r in hg.edges.collect()} == {(1, 15, 1), (2, 5, 1), (3, 2, 1), (None, 6, 1)}
    assert hg.pins._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[-1].count("Exchange") <= 1
