"""Registered queries of the partitioning engine and their SQL equivalents."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgpart import model, surround
from hgpart.model import Hypergraph, Limits
from hgpart.operators import candidates, contract, matching, metrics, moves, multilevel, sequence
from hgpart.oracle import sql as oracle
from hgpart.oracle.sql import compose, graph
from hgpart.plans.checkpoints import materialize
from hgpart.sources.builders import BUILDERS, REGIMES, limits_of
from hgpart.streaming import streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}

#: The workload on which single steps are shown, and the number of parts of its fixed assignment.
STEP, PARTS = "basket", 200
ASSIGN_SQL = f"SELECT n, n % {PARTS} AS p FROM nodes"


def _add(name: str, query: Callable, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLE[name] = sql


def _step(name: str, query: Callable[[Hypergraph, Limits], DataFrame], final: str | None, workload: str = STEP, bound: str = "is_dst", levels: int = 3, keep: bool = False) -> None:
    """A query on a workload's hypergraph and limits. keep: the hypergraph is written once, for queries that read it again and again."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        hg = BUILDERS[workload](spark, sf_dir)
        hg = multilevel.kept(hg) if keep else hg
        return query(hg, limits_of(workload, hg))

    _add(name, run, final and compose(graph(workload, levels, bound, ASSIGN_SQL), final))


def modulo(hg: Hypergraph, parts: int = PARTS) -> DataFrame:
    """A fixed assignment, blind to structure: the sanity floor."""
    return hg.nodes.select("n", F.pmod("n", F.lit(parts)).alias("p"))


# model
_step("hg_pins", lambda hg, _: hg.pins, "SELECT e, n, is_src, is_dst FROM pins")
_step("hg_incidence_sizes", lambda hg, _: model.incidence_sizes(hg), "SELECT n, coalesce(count(e) FILTER (WHERE is_dst), 0) AS n_in, coalesce(count(e) FILTER (WHERE is_src), 0) AS n_out, count(e) AS n_all FROM nodes LEFT JOIN pins USING (n) GROUP BY n")
_step("hg_neighbors", lambda hg, _: model.neighbors(hg), "SELECT DISTINCT a.n, b.n AS m FROM pins a JOIN pins b ON a.e = b.e AND a.n <> b.n")
_step("hg_csr_offsets", lambda hg, _: model.to_csr(model.to_packed(hg.pins, "e", "n")), "SELECT e AS id, (sum(c) OVER (ORDER BY e) - c)::BIGINT AS start, c AS length FROM (SELECT e, count(*) AS c FROM pins GROUP BY e)")
_step("hg_packed_roundtrip", lambda hg, _: model.from_packed(model.to_packed(hg.pins, "e", "n"), "e", "n"), "SELECT e, n FROM pins")
_step("hg_validate", model.validate, "SELECT problem, n_rows FROM (VALUES ('duplicate_pins', 0::BIGINT), ('negative_weights', 0), ('pins_without_edge', 0), ('pins_without_node', 0), ('oversized_nodes', 0), ('overbound_nodes', 0)) t(problem, n_rows)")
_STATS = (
    "SELECT (SELECT count(*) FROM nodes) AS n_nodes, count(*) AS n_edges, sum(s)::BIGINT AS n_pins, max(s) AS max_edge, sum(s * (s - 1) // 2)::BIGINT AS n_pairs, count(*) FILTER (WHERE s = 1) AS n_single, "
    "(SELECT coalesce(max(d), 0) FROM (SELECT count(*) AS d FROM pins WHERE is_dst GROUP BY n)) AS max_in FROM (SELECT count(*) AS s FROM pins GROUP BY e)"
)
_step("hg_stats", lambda hg, _: model.stats(hg), _STATS)
_add(
    "hg_dense_ids",
    lambda spark, d: model.assign_ids(spark.read.parquet(f"{d}/customer.parquet"), "c_name"),
    "SELECT c_name, row_number() OVER (ORDER BY c_name) - 1 AS id FROM (SELECT DISTINCT c_name FROM customer)",
)

# candidates
_HIST = "SELECT n, m, hist, shared_in FROM conn0"
_PROP = "SELECT n, cand, score FROM prop0"
_step("coarsen_histogram", lambda hg, lim: candidates.connection_histogram(hg, lim), _HIST)
_step("coarsen_histogram_mat", lambda hg, lim: candidates.connection_histogram(hg, lim, materialize(model.neighbors(hg))), _HIST)
_step("cand_heavy_light", lambda hg, lim: candidates.histogram_heavy_light(hg, lim, 8), _HIST)
_step("cand_heavy_proposals", lambda hg, lim: candidates.propose_candidates(hg, lim, chunk=64, bounds=(1 << 30, 1 << 30)), _PROP, "sourcing", keep=True)
_step("hg_neighbors_heavy", lambda hg, _: model.neighbors(hg, 8), "SELECT DISTINCT a.n, b.n AS m FROM pins a JOIN pins b ON a.e = b.e AND a.n <> b.n")
_step("cand_scaled", lambda hg, _: candidates.scaled_histogram(hg), "SELECT a.n, b.n AS m, sum(w * 1000000 // (s - 1))::BIGINT AS hist FROM pins a JOIN pins b ON a.e = b.e AND a.n < b.n JOIN edges x ON x.e = a.e JOIN (SELECT e, count(*) AS s FROM pins GROUP BY e) z ON z.e = a.e GROUP BY a.n, b.n")
_step(
    "pair_union_size",
    lambda hg, lim: candidates.with_unions(candidates.connection_histogram(hg, lim), candidates.node_loads(hg, lim)).select("n", "m", "union_nodes", "union_inbound"),
    "SELECT c.n, c.m, a.size + b.size AS union_nodes, a.deg + b.deg - shared_in AS union_inbound FROM conn0 c JOIN load0 a ON a.n = c.n JOIN load0 b ON b.n = c.m",
)
_step("pair_union_arrays", lambda hg, _: candidates.pair_unions_by_arrays(hg), "SELECT c.n, c.m, a.deg + b.deg - shared_in AS union_inbound FROM conn0 c JOIN load0 a ON a.n = c.n JOIN load0 b ON b.n = c.m")
_step("coarsen_candidates", candidates.propose_candidates, _PROP)
_step("cand_batched", candidates.propose_batched, _PROP)
_step("cand_deferred", candidates.propose_deferred, _PROP)
for _kind, _column, _on in (("out", "is_src", "trade"), ("incident", "incident", "links")):
    _step(
        f"cand_{_kind}_bound",
        lambda hg, lim, kind=_kind: candidates.propose_candidates(hg, Limits(lim.max_nodes, lim.max_inbound, kind)),
        _PROP,
        _on,
        _column,
    )


# matching and contraction
def _proposal(hg: Hypergraph, lim: Limits) -> DataFrame:
    return materialize(candidates.propose_candidates(hg, lim), "proposal")


_MATCHED = "SELECT n, mate FROM matched0"
_step("match_roots", lambda hg, lim: matching.two_cycles(_proposal(hg, lim)), "SELECT n, cand AS mate FROM root0")
_step("match_winners", lambda hg, lim: matching.winners(_proposal(hg, lim)), "SELECT cand, score, n FROM win0")
_step("match_two_pass", lambda hg, lim: matching.match_pairs(_proposal(hg, lim), "levels"), _MATCHED)
_step("match_doubling", lambda hg, lim: matching.match_pairs(_proposal(hg, lim), "doubling"), _MATCHED)
_step("match_exact_weight", lambda hg, lim: matching.matching_weight(p := _proposal(hg, lim), matching.match_exact(p)), None)
_step(
    "match_violations",
    lambda hg, lim: matching.check_matching(p := _proposal(hg, lim), matching.match_pairs(p)),
    "SELECT * FROM (VALUES ('falling_scores', 0::BIGINT), ('long_cycles', 0), ('not_mutual', 0), ('matched_twice', 0)) t(rule, n_rows)",
)


def _rematch(hg: Hypergraph, lim: Limits, rounds: int = 2) -> DataFrame:
    """Free nodes propose again among free nodes, before contracting; changes the result, so off by default."""
    valid = candidates.mirrored(candidates.pair_valid(candidates.with_unions(candidates.connection_histogram(hg, lim), candidates.node_loads(hg, lim)), lim))
    valid, found = materialize(valid, "valid"), None
    for _ in range(rounds):
        free = valid if found is None else valid.join(found.select("n"), "n", "left_anti").join(found.select(F.col("n").alias("cand")), "cand", "left_anti")
        got = materialize(matching.match_pairs(materialize(model.argmax_by(free, "n", "score", "cand").select("n", "cand", "score"))), "matched")
        found = got if found is None else materialize(found.unionByName(got), "matched")
    return found


_step("match_rematch", _rematch, None)


def _matching_ratio(hg: Hypergraph, lim: Limits) -> DataFrame:
    p = _proposal(hg, lim)
    two = matching.matching_weight(p, matching.match_pairs(p)).select(F.col("weight").alias("two_pass"))
    return two.crossJoin(F.broadcast(matching.matching_weight(p, matching.match_exact(p)).select(F.col("weight").alias("exact")))).withColumn("ratio", F.col("two_pass") / F.col("exact"))


_step("measure_matching_ratio", _matching_ratio, None)


def _gamma(hg: Hypergraph, lim: Limits) -> DataFrame:
    return materialize(contract.coarse_map(hg.nodes, matching.match_pairs(_proposal(hg, lim))), "gamma")


_step("contract_gamma", _gamma, "SELECT n, c FROM gamma0")
_step("contract_pins", lambda hg, lim: contract.contract(hg, _gamma(hg, lim)).pins, "SELECT e, n, is_src, is_dst FROM pins1")
_step("contract_sizes", lambda hg, lim: contract.contract(hg, _gamma(hg, lim)).nodes, "SELECT n, size FROM nodes1")
_step("contract_neighbors", lambda hg, lim: contract.contract_neighbors(model.neighbors(hg), _gamma(hg, lim)), "SELECT DISTINCT a.n, b.n AS m FROM pins1 a JOIN pins1 b ON a.e = b.e AND a.n <> b.n")
_step(
    "contract_merge_parallel",
    lambda hg, _: model.merge_parallel(hg).edges,
    "SELECT min(e) AS e, sum(w)::BIGINT AS w, count(*)::INT AS mult FROM edges JOIN (SELECT e, list((n, is_src, is_dst) ORDER BY n) AS k FROM pins GROUP BY e) USING (e) GROUP BY k",
    "links",
)
for _k in (1, 2, 3):
    _step(
        f"coarsen_level{_k}",
        lambda hg, lim, k=_k: multilevel.coarsen(hg, lim, max_levels=k)[-1].graph.nodes,
        f"SELECT n, size FROM nodes{_k}",
        levels=_k,
    )
_step(
    "initial_partition",
    lambda hg, lim: multilevel.initial_assignment(multilevel.coarsen(hg, lim, max_levels=3)),
    "SELECT a.n, c.c AS p FROM gamma0 a JOIN gamma1 b ON b.n = a.c JOIN gamma2 c ON c.n = b.c",
)


def _levels(hg: Hypergraph, lim: Limits) -> DataFrame:
    reports = multilevel.HypergraphPartitioner(lim).fit(hg).reports
    return hg.pins.sparkSession.createDataFrame(reports, "level int, n_nodes long, n_pins long, connectivity long, n_moves long")


_step("coarsen_levels", _levels, None)
_step("measure_level_costs", multilevel.level_costs, None)


# refinement from a fixed assignment
def _fixed(step: Callable, parts: int = PARTS) -> Callable[[Hypergraph, Limits], DataFrame]:
    """step(hg, limits, assign, pe) with pe written once."""

    def run(hg: Hypergraph, lim: Limits) -> DataFrame:
        assign = modulo(hg, parts)
        return step(hg, lim, assign, materialize(moves.partition_pins(hg, assign, lim), "pe"))

    return run


def _seq(hg, lim, assign, pe):
    return materialize(sequence.sequence_moves(moves.propose_moves(hg, assign, pe, lim)), "seq")


def _transitions(hg, lim, assign, pe, seq):
    return sequence.inbound_transitions(sequence.inbound_events(hg, seq, lim), pe)


def _flips(hg, lim, assign, pe, seq):
    return sequence.validity_flips(sequence.size_events(hg, seq), _transitions(hg, lim, assign, pe, seq), moves.partition_loads(hg, assign, pe), lim)


def _violations(hg, lim, assign, pe, seq):
    return sequence.active_violations(seq, _flips(hg, lim, assign, pe, seq), moves.partition_loads(hg, assign, pe), lim)


def _with_seq(step: Callable) -> Callable:
    return _fixed(lambda hg, lim, assign, pe: step(hg, lim, assign, pe, _seq(hg, lim, assign, pe)))


_step("refine_pe_counts", _fixed(lambda hg, lim, a, pe: pe), "SELECT e, p, cnt, cnt_in FROM pe")
_step("refine_inbound_sizes", _fixed(lambda hg, lim, a, pe: moves.partition_loads(hg, a, pe)), "SELECT p, size, inbound FROM loads")
_step("refine_saving", _fixed(lambda hg, lim, a, pe: moves.savings(hg, a, pe)), "SELECT n, ps, saving, total FROM sav")
_step("refine_gains", _fixed(lambda hg, lim, a, pe: moves.gains(hg, a, pe)), "SELECT n, ps, p, gain FROM gain")
_step("refine_moves", _fixed(lambda hg, lim, a, pe: moves.propose_moves(hg, a, pe, lim)), "SELECT n, ps, pd, gain FROM mv")
_step("refine_sequence", _with_seq(lambda hg, lim, a, pe, s: s), "SELECT idx, n, ps, pd, gain FROM seq")
_SG = "SELECT idx, n, ps, pd, gain, seq_gain FROM sg"
_step("refine_seq_gain", _with_seq(lambda hg, lim, a, pe, s: sequence.sequence_gains(hg, s, pe, "pairs")), _SG)
_step("refine_seq_gain_scan", _with_seq(lambda hg, lim, a, pe, s: sequence.sequence_gains(hg, s, pe, "scan")), _SG)
_step("refine_seq_gain_literal", _with_seq(lambda hg, lim, a, pe, s: sequence.sequence_gains(hg, s, pe, "scan", "literal_or")), "SELECT idx, n, ps, pd, gain, seq_gain FROM sg_or")
_step("events_size", _with_seq(lambda hg, lim, a, pe, s: sequence.size_events(hg, s)), "SELECT p, idx, delta, total FROM se")
_step("events_inbound", _with_seq(lambda hg, lim, a, pe, s: sequence.inbound_events(hg, s, lim).drop("mult")), "SELECT p, e, idx, delta, total FROM ie")
_step("events_distinct_inbound", _with_seq(_transitions), "SELECT p, idx, delta, total FROM tr")
_step("events_flips", _with_seq(_flips), "SELECT kind, p, idx, flip FROM fl")
_step("events_violations", _with_seq(_violations), "SELECT idx, viol FROM av")
#: Blocks of the scans that spread a crowded partition's events over tasks.
_BLOCK = 64
_step("events_size_blocked", _with_seq(lambda hg, lim, a, pe, s: sequence.size_events(hg, s, _BLOCK)), "SELECT p, idx, delta, total FROM se")
_step("events_distinct_inbound_blocked", _with_seq(lambda hg, lim, a, pe, s: sequence.inbound_transitions(sequence.inbound_events(hg, s, lim), pe, _BLOCK)), "SELECT p, idx, delta, total FROM tr")
_step("events_flips_blocked", _with_seq(lambda hg, lim, a, pe, s: sequence.validity_flips(sequence.size_events(hg, s), _transitions(hg, lim, a, pe, s), moves.partition_loads(hg, a, pe), lim, _BLOCK)), "SELECT kind, p, idx, flip FROM fl")


def _best(hg, lim, a, pe, s):
    return sequence.best_prefix(sequence.sequence_gains(hg, s, pe), _violations(hg, lim, a, pe, s))


_step("refine_best_prefix", _with_seq(_best), "SELECT cut, total FROM bp")
_step("refine_apply", lambda hg, lim: multilevel.refine_once(hg, modulo(hg), lim)[0], "SELECT n, p FROM app")
_step("refine_project", lambda hg, lim: sequence.project(contract.contract(hg, g := _gamma(hg, lim)).nodes.select("n", F.pmod("n", F.lit(PARTS)).alias("p")), g), f"SELECT n, c % {PARTS} AS p FROM gamma0")
_CONN = "SELECT coalesce(sum(w * (parts - 1)), 0)::BIGINT AS connectivity FROM edges JOIN (SELECT e, count(DISTINCT p) AS parts FROM pins JOIN {a} USING (n) GROUP BY e) USING (e)"


def _gain_identity(hg, lim, a, pe, s):
    """Connectivity before and after, and what the sequence promised: before - after = promised."""
    s = materialize(s)
    cut, total = _best(hg, lim, a, pe, s).first()
    after = sequence.apply_moves(a, s, cut)
    before = metrics.connectivity(hg, a).withColumnRenamed("connectivity", "before")
    return before.crossJoin(F.broadcast(metrics.connectivity(hg, after).withColumnRenamed("connectivity", "after"))).withColumn("promised", F.lit(total).cast("bigint"))


_step("measure_gain_identity", _with_seq(_gain_identity), f"SELECT ({_CONN.format(a='assign')}) AS before, ({_CONN.format(a='app')}) AS after, (SELECT total FROM bp) AS promised")

# measures of the fixed assignment
_step("base_modulo", lambda hg, _: modulo(hg), "SELECT n, p FROM assign")
_step("measure_connectivity", lambda hg, _: metrics.connectivity(hg, modulo(hg)), _CONN.format(a="assign"))
_step("measure_lambda", lambda hg, _: metrics.spans(hg, modulo(hg)), "SELECT e, count(DISTINCT p) AS parts FROM pins JOIN assign USING (n) GROUP BY e")
_step("measure_partition_count", lambda hg, lim: metrics.partition_count(hg, modulo(hg), lim), "SELECT count(DISTINCT p) AS n_parts, (SELECT ceil(sum(size) / max(om))::BIGINT FROM nodes, lim) AS lower_bound FROM assign")
_step("measure_constraints", lambda hg, lim: metrics.constraint_report(hg, modulo(hg), lim), "SELECT p, size, inbound, om - size AS free_nodes, de - inbound AS free_inbound, size > om OR inbound > de AS broken FROM loads, lim")
_step("measure_cut", lambda hg, _: metrics.cut_measures(hg, modulo(hg)), "SELECT coalesce(sum(w) FILTER (WHERE parts > 1), 0)::BIGINT AS cut_weight, coalesce(sum(w * parts) FILTER (WHERE parts > 1), 0)::BIGINT AS external_degree, coalesce(sum(w) FILTER (WHERE parts = 1), 0)::BIGINT AS absorbed_weight FROM edges JOIN (SELECT e, count(DISTINCT p) AS parts FROM pins JOIN assign USING (n) GROUP BY e) USING (e)")
_step("measure_pair_volume", lambda hg, _: metrics.pair_volume(hg), "SELECT 2 * count(*) AS pairs, 16 * count(*) AS neighbour_bytes, 32 * count(*) AS bin_bytes FROM conn0")


# whole runs
def _run(name: str, query: Callable[[Hypergraph, Limits], DataFrame], workload: str = STEP) -> None:
    """As _step without SQL; the hypergraph is written once, as a whole run and its measures read it again and again."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        hg = multilevel.kept(BUILDERS[workload](spark, sf_dir))
        return query(hg, limits_of(workload, hg))

    _add(name, run)


def _fit(hg: Hypergraph, lim: Limits, **opts) -> DataFrame:
    return multilevel.HypergraphPartitioner(lim, **opts).fit(hg).assign


def _scored(hg: Hypergraph, lim: Limits, assign: DataFrame, label: str) -> DataFrame:
    return metrics.summary(hg, materialize(assign, "assign"), lim).withColumn("method", F.lit(label))


_run("multilevel_partition", _fit, "terms")
_step("multilevel_distributed", lambda hg, lim: multilevel.refine(multilevel.coarsen(hg, lim, max_levels=3), lim).assign, None, keep=True)
ORACLE["multilevel_distributed"] = compose(oracle.multilevel(STEP, 3), "SELECT n, p FROM app_0")
_run("multilevel_refine", lambda hg, lim: _fit(hg, lim, passes=3), "terms")
_run("ablate_no_refinement", lambda hg, lim: _scored(hg, lim, _fit(hg, lim, refine=False), "no refinement"), "terms")
_run("ablate_no_inbound_limit", lambda hg, lim: _scored(hg, l2 := Limits(lim.max_nodes), _fit(hg, l2), "size only"), "terms")
_run("ablate_no_size_limit", lambda hg, lim: _scored(hg, l2 := Limits(max_inbound=lim.max_inbound), _fit(hg, l2), "inbound only"), "terms")
_step("ablate_merged_edges", lambda hg, lim: _scored(hg, lim, _fit(hg, lim, merge=True), "merged"), None, "links")
_step("ablate_materialized_neighbors", lambda hg, lim: multilevel.initial_assignment(multilevel.coarsen(hg, lim, 2, materialize_neighbors=True)), "SELECT a.n, b.c AS p FROM gamma0 a JOIN gamma1 b ON b.n = a.c")
_step("ablate_deferred_checks", lambda hg, lim: multilevel.initial_assignment(multilevel.coarsen(hg, lim, 2, deferred=3)), "SELECT a.n, b.c AS p FROM gamma0 a JOIN gamma1 b ON b.n = a.c")


def _baseline(method: str, **opts):
    return lambda hg, lim: multilevel.run_local(hg, lim, method, **opts).select(F.col("a").alias("n"), F.col("b").alias("p"))


_run("base_sequential", _baseline("sequential"), "terms")
_step("base_overlap", _baseline("overlap"), None, "terms")
_step("base_overlap_newest", _baseline("overlap", fallback="newest"), None, "terms")
_step("base_one_pass", _baseline("one_pass"), None, "terms")
ORACLE["base_one_pass"] = oracle.one_pass("terms")
_step("base_one_pass_blocks", lambda hg, lim: multilevel.one_pass_blocks(hg, lim, 250), None, "terms")
ORACLE["base_one_pass_blocks"] = oracle.one_pass("terms", 250)
_step("base_one_pass_size_only", lambda hg, lim: _baseline("one_pass")(hg, Limits(lim.max_nodes)), "SELECT n, n // 16 * 16 AS p FROM nodes")


def compare(spark: SparkSession, sf_dir: str, names=tuple(BUILDERS)) -> DataFrame:
    """(workload, method, connectivity, n_parts, max_size, max_inbound, n_broken, ratio, geometric, arithmetic): ratio is
    the multi-level method's connectivity over the method's (both 0: 1), the last two its means over the workloads; a
    connectivity of 0 on one side only is left as it is, so that the geometric mean may be 0."""
    out = None
    for name in names:
        hg = multilevel.kept(BUILDERS[name](spark, sf_dir))
        lim = limits_of(name, hg)
        for method in ("multilevel", "sequential", "overlap", "one_pass"):
            assign = _fit(hg, lim) if method == "multilevel" else _baseline(method)(hg, lim)
            one = _scored(hg, lim, assign, method).withColumn("workload", F.lit(name))
            out = one if out is None else out.unionByName(one)
    rows = materialize(out, "compare")
    own = rows.filter("method = 'multilevel'").select("workload", F.col("connectivity").alias("own"))
    ratio = F.when((F.col("own") == 0) & (F.col("connectivity") == 0), 1.0).otherwise(F.col("own") / F.greatest(F.col("connectivity"), F.lit(1)))
    ratios = rows.join(own, "workload").select("workload", "method", "connectivity", "n_parts", "max_size", "max_inbound", "n_broken", ratio.alias("ratio"))
    geometric = F.when(F.min("ratio") > 0, F.exp(F.avg(F.log("ratio")))).otherwise(0.0)
    return ratios.join(ratios.groupBy("method").agg(geometric.alias("geometric"), F.avg("ratio").alias("arithmetic")), "method").select(*ratios.columns, "geometric", "arithmetic")


_add("measure_relative", compare)


def scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pins against seconds of coarsening and refining ever larger shares of one workload, with slope and fit."""
    import time

    hg = multilevel.kept(BUILDERS["basket"](spark, sf_dir))
    rows = []
    for share in (4, 2, 1):
        part = Hypergraph(materialize(hg.pins.filter(F.pmod("e", F.lit(share)) == 0)), hg.edges, hg.nodes)
        began = time.time()
        materialize(_fit(part, limits_of("basket", part)))
        rows.append((share, part.pins.count(), time.time() - began))
    df = spark.createDataFrame(rows, "share int, n_pins long, seconds double")
    fit = df.agg(F.regr_slope("seconds", "n_pins").alias("slope"), F.regr_r2("seconds", "n_pins").alias("r2"))
    return df.crossJoin(F.broadcast(fit))  # one row


_add("measure_scaling", scaling)

for _name in REGIMES:
    _step(f"wl_{_name}_stats", lambda hg, _: model.stats(hg), _STATS, _name)
    _step(f"wl_{_name}_coarsen1", lambda hg, lim: contract.contract(hg, _gamma(hg, lim)).nodes, "SELECT n, size FROM nodes1", _name, keep=True)
    # the layered network has so many nodes that 200 parts would all be full
    _parts = 10_000 if _name == "layered" else PARTS
    _step(f"wl_{_name}_moves", _fixed(lambda hg, lim, a, pe: moves.propose_moves(hg, a, pe, lim), _parts), None, _name)
    ORACLE[f"wl_{_name}_moves"] = compose(graph(_name, 0, "is_dst", f"SELECT n, n % {_parts} AS p FROM nodes"), "SELECT n, ps, pd, gain FROM mv")
    _run(f"wl_{_name}_summary", lambda hg, lim: _scored(hg, lim, _fit(hg, lim), "multilevel"), _name)
    _step(f"wl_{_name}_two_levels", lambda hg, lim: _fit(hg, lim, max_levels=2), None, _name, keep=True)
    ORACLE[f"wl_{_name}_two_levels"] = compose(oracle.multilevel(_name, 2), "SELECT n, p FROM app_0")

# parallel patterns
_add(
    "pat_segmented_scan",
    lambda spark, d: model.segmented_scan(spark.read.parquet(f"{d}/events.parquet").select("user_id", "event_id", F.lit(1).cast("bigint").alias("one")), ["user_id"], "event_id", "one", "running").drop("one"),
    "SELECT user_id, event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id) AS running FROM events",
)
_add(
    "pat_global_scan",
    lambda spark, d: model.global_scan(
        model.global_rank(spark.read.parquet(f"{d}/orders.parquet").select("o_orderkey", "o_custkey"), F.col("o_custkey").desc(), F.col("o_orderkey").asc()), "idx", "o_custkey", "running", 1024
    ),
    "SELECT o_orderkey, o_custkey, row_number() OVER w AS idx, (sum(o_custkey) OVER w)::BIGINT AS running FROM orders WINDOW w AS (ORDER BY o_custkey DESC, o_orderkey ROWS UNBOUNDED PRECEDING)",
)
_add(
    "pat_argmax",
    lambda spark, d: model.argmax_by(spark.read.parquet(f"{d}/lineitem.parquet").select("l_suppkey", F.col("l_quantity").cast("bigint").alias("q"), "l_partkey"), "l_suppkey", "q", "l_partkey"),
    "SELECT l_suppkey, q, l_partkey FROM (SELECT l_suppkey, l_quantity::BIGINT AS q, l_partkey, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_quantity DESC, l_partkey DESC) AS r FROM lineitem) WHERE r = 1",
)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    hg = BUILDERS["basket"](spark, sf_dir)
    lim = limits_of("basket", hg)
    return _scored(hg, lim, _fit(hg, lim), "multilevel")


_add("multilevel_summary", flagship)


def queries() -> dict:
    return QUERIES | surround.QUERIES | streams.QUERIES


def oracle_sql() -> dict:
    return ORACLE | surround.ORACLE | streams.ORACLE
