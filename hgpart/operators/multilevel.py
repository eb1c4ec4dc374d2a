"""The multi-level partitioner: coarsen, take the coarsest nodes as partitions, refine on the way back."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.model import NO_LIMIT, Hypergraph, Limits, merge_parallel, neighbors
from hgpart.operators import candidates, contract, dealt, local, matching, metrics, moves, sequence
from hgpart.plans.checkpoints import forget, materialize
from hgpart.plans.costs import counted

#: A level with at most so many pins and co-pin pairs runs in one task, and so do all coarser ones.
LOCAL_PINS = 4_000_000
LOCAL_PAIRS = 60_000_000
#: A level beyond these with at most so many nodes, pins and co-pin pairs, and all coarser ones, have their nodes' arrays in the driver and their pins dealt to tasks.
DEALT_NODES, DEALT_PINS, DEALT_PAIRS = 4_000_000, 100_000_000, 8_000_000_000
#: A round of more moves scans its events in blocks of so many, so that a partition that draws most of them is spread over tasks.
EVENT_BLOCK = 1 << 18


@dataclass(frozen=True)
class Level:
    graph: Hypergraph
    gamma: DataFrame | None


@dataclass(frozen=True)
class PartitionResult:
    assign: DataFrame
    reports: list[tuple] = field(default_factory=list)


def kept(hg: Hypergraph) -> Hypergraph:
    """hg with its tables written; those that are stay as they are."""
    once = lambda df, label: df if getattr(df, "written_at", None) else materialize(df, label)
    return Hypergraph(once(hg.pins, "pins"), once(hg.edges, "edges"), once(hg.nodes, "nodes"))


def pair_volume(hg: Hypergraph) -> tuple[int, int]:
    return volume(hg)[:2]


def volume(hg: Hypergraph) -> tuple[int, int, int]:
    """Pins, co-pin pairs and pins of the largest hyperedge; counted once for a written table."""
    if (known := getattr(hg.pins, "volume", None)) is None:
        row = hg.pins.groupBy("e").agg(F.count(F.lit(1)).alias("s")).agg(F.sum("s"), F.sum(F.expr("s * (s - 1) div 2")), F.max("s")).first()
        known = tuple(int(x or 0) for x in row)
        if getattr(hg.pins, "written_at", None):
            hg.pins.volume = known
    return known


def fits_locally(hg: Hypergraph, local_pins: int = LOCAL_PINS, local_pairs: int = LOCAL_PAIRS) -> bool:
    pins, pairs = pair_volume(hg)
    return pins <= local_pins and pairs <= local_pairs


def run_local(hg: Hypergraph, limits: Limits, method: str = "multilevel", **opts) -> DataFrame:
    """(kind, level, a, b, c, d) from one task: "assign" rows (a = n, b = p) and, for "multilevel", "level" rows
    (nodes, pins, connectivity, moves). For hypergraphs that fits_locally admits, and sequential baselines."""
    row = lambda kind, x, y, u: [F.lit(kind).cast("byte").alias("kind"), F.col(x).alias("x"), F.col(y).alias("y"), u.cast("bigint").alias("u")]
    packed = (
        hg.pins.select(*row(0, "e", "n", F.col("is_src").cast("int") * 2 + F.col("is_dst").cast("int")))
        .unionByName(hg.edges.select(*row(1, "e", "w", F.col("mult"))))
        .unionByName(hg.nodes.select(*row(2, "n", "size", F.lit(0))))
    )

    def solve(rows: pa.Table) -> pa.Table:
        import numpy as np
        import pyarrow.compute as pc

        def of(kind: int) -> list[np.ndarray]:
            own = rows.filter(pc.equal(rows.column("kind"), kind))
            x, y, u = (own.column(c).to_numpy() for c in ("x", "y", "u"))
            order = np.argsort(x, kind="stable")
            return [c[order] for c in (x, y, u)]

        (edge_ids, w, mult), (node_ids, size, _), (e, n, flags) = of(1), of(2), of(0)
        del rows
        e, n = np.searchsorted(edge_ids, e), np.searchsorted(node_ids, n)
        g = local.Graph(e, n, flags > 1, flags % 2 > 0, w, mult, size, limits.bound_on)
        del e, n, flags
        pa.default_memory_pool().release_unused()
        report: list[tuple] = []
        if method == "multilevel":
            p, report = local.multilevel(g, limits.max_nodes, limits.max_inbound, **opts)
        else:
            p = {"sequential": local.sequential, "overlap": local.overlap, "one_pass": local.one_pass}[method](g, limits.max_nodes, limits.max_inbound, **opts)
        zero = np.zeros(len(node_ids), np.int64)
        out = [("assign",) * len(node_ids), zero, node_ids, node_ids[p], zero, zero]
        if report:
            out = [np.concatenate([x, np.array(y)]) for x, y in zip(out, (("level",) * len(report), *zip(*report)))]
        kinds = (pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
        return pa.table({c: pa.array(x, t) for c, x, t in zip(("kind", "level", "a", "b", "c", "d"), out, kinds)})

    return packed.groupBy(F.lit(0).alias("all")).applyInArrow(solve, "kind string, level int, a long, b long, c long, d long")


def largest_edge(hg: Hypergraph) -> int:
    return volume(hg)[2]


def one_pass_blocks(hg: Hypergraph, limits: Limits, width: int) -> DataFrame:
    """(n, p): the one-pass filler over ranges of `width` node ids side by side; a range costs one partition more at most."""
    load = hg.weighted_pins.filter(limits.bound()).select("n", "e", "mult")
    rows = hg.nodes.join(load, "n", "left").withColumn("range", F.floor(F.col("n") / F.lit(width)))

    def fill(pdf: pd.DataFrame) -> pd.DataFrame:
        out, at, size, held, full = [], None, 0, set(), 0
        for n, own in pdf.sort_values("n", kind="stable").groupby("n", sort=True):
            bounding = {int(e): int(m) for e, m in zip(own["e"], own["mult"]) if e == e and m == m}
            more = sum(m for e, m in bounding.items() if e not in held)
            here = int(own["size"].iloc[0])
            if at is None or size + here > limits.max_nodes or full + more > limits.max_inbound:
                at, size, held, full = int(n), 0, set(), 0
                more = sum(bounding.values())
            held.update(bounding)
            size, full = size + here, full + more
            out.append((int(n), at))
        return pd.DataFrame(out, columns=["n", "p"])

    return rows.groupBy("range").applyInPandas(fill, "n long, p long")


def coarsen(hg: Hypergraph, limits: Limits, max_levels: int | None = None, materialize_neighbors: bool = False, deferred: int = 0, match: str = "doubling", until: Callable[[Hypergraph], bool] | None = None) -> list[Level]:
    """Levels, finest first; the last has gamma None. Stops at ceil(total size / max_nodes) nodes, when nothing merges, or at a level
    of which `until` holds."""
    hg = kept(hg)
    total = hg.nodes.agg(F.sum("size")).first()[0] or 0
    target = 1 if limits.max_nodes >= NO_LIMIT else -(-total // limits.max_nodes)
    # coarse nodes bear the id of a member and hyperedges keep their weights, so these bounds hold on all levels
    bounds = (int(hg.edges.agg(F.sum("w")).first()[0] or 0), int(hg.nodes.agg(F.max("n")).first()[0] or 0))
    chunk = lambda h: candidates.HEAVY_PINS if largest_edge(h) > candidates.HEAVY_PINS else None
    nbrs = materialize(neighbors(hg, chunk(hg)), "neighbors") if materialize_neighbors else None
    levels: list[Level] = []
    while (max_levels is None or len(levels) < max_levels) and not (until and until(hg)) and hg.nodes.count() > target:
        proposal = candidates.propose_deferred(hg, limits, deferred, chunk(hg)) if deferred else candidates.propose_candidates(hg, limits, nbrs, chunk(hg), bounds)
        proposal = materialize(proposal, "proposal")
        if proposal.isEmpty():
            break
        gamma = materialize(contract.coarse_map(hg.nodes, matching.match_pairs(proposal, match)), "gamma")
        levels.append(Level(hg, gamma))
        if nbrs is not None:
            nbrs = materialize(contract.contract_neighbors(nbrs, gamma), "neighbors")
        hg = kept(contract.contract(hg, gamma))
    return [*levels, Level(hg, None)]


def level_costs(hg: Hypergraph, limits: Limits, max_levels: int = 2) -> DataFrame:
    """(level, n_nodes, n_pins, n_pairs, largest, jobs, stages, tasks, seconds): each distributed level's size, and what coarsening it cost."""
    rows = []
    for k in range(max_levels):
        pins, pairs = pair_volume(hg)
        size = (k, hg.nodes.count(), pins, pairs, largest_edge(hg))
        with counted(hg.pins.sparkSession, f"level-{k}") as cost:
            levels = coarsen(hg, limits, 1)
        rows.append((*size, cost["jobs"], cost["stages"], cost["tasks"], cost["seconds"]))
        if len(levels) == 1:
            break
        hg = levels[-1].graph
    return hg.pins.sparkSession.createDataFrame(rows, "level int, n_nodes long, n_pins long, n_pairs long, largest long, jobs int, stages int, tasks int, seconds double")


def initial_assignment(levels: list[Level], start: DataFrame | None = None) -> DataFrame:
    """(n, p) of the finest nodes: the coarsest node that each ends in, or what start (n, p) says of that node."""
    assign = levels[-1].graph.nodes.select("n", F.col("n").alias("p")) if start is None else start
    for level in reversed(levels[:-1]):
        assign = sequence.project(assign, level.gamma)
    return assign


def refine_once(hg: Hypergraph, assign: DataFrame, limits: Limits, admit: str = "not_full", min_gain: int = 1, prefix_tie: str = "longest", form: str = "independent", method: str = "scan", event_block: int = EVENT_BLOCK) -> tuple[DataFrame, int, int]:
    """One round on one level: (partitions, gained, moves made)."""
    pe = materialize(moves.partition_pins(hg, assign, limits), "pe")
    seq = materialize(sequence.sequence_moves(moves.propose_moves(hg, assign, pe, limits, admit, min_gain)), "seq")
    if not (n_moves := seq.count()):
        return assign, 0, 0
    block = event_block if n_moves > event_block else None
    gained = materialize(sequence.sequence_gains(hg, seq, pe, method, form), "gained")
    loads = materialize(moves.partition_loads(hg, assign, pe), "loads")
    transitions = sequence.inbound_transitions(sequence.inbound_events(hg, seq, limits), pe, block)
    flips = sequence.validity_flips(sequence.size_events(hg, seq, block), transitions, loads, limits, block)
    cut, total = sequence.best_prefix(gained, sequence.active_violations(seq, flips, loads, limits), prefix_tie).first()
    if cut:
        assign = materialize(sequence.apply_moves(assign, seq, cut), "assign")
    forget(pe, seq, gained, loads)
    return assign, int(total or 0) if cut else 0, int(cut or 0)


def refine(levels: list[Level], limits: Limits, passes: int = 1, start: DataFrame | None = None, **opts) -> PartitionResult:
    """Up to `passes` rounds a level; 0: until nothing moves. Reports: level, nodes, pins, connectivity after it, moves.

    start: partitions (n, p) of the last level's nodes, if that level is refined already."""
    assign = levels[-1].graph.nodes.select("n", F.col("n").alias("p")) if start is None else start
    reports = []
    for k in range(len(levels) - 1 if start is None else len(levels) - 2, -1, -1):
        if levels[k].gamma is not None:
            assign = materialize(sequence.project(assign, levels[k].gamma), "assign")
        made = 0
        for _ in range(passes if passes else 1 << 30):
            assign, gained, n = refine_once(levels[k].graph, assign, limits, **opts)
            made += n
            if not n:
                break
        graph = levels[k].graph
        reports.append((k, graph.nodes.count(), graph.pins.count(), int(metrics.connectivity(graph, assign).first()[0] or 0), made))
    return PartitionResult(assign, reports)


class HypergraphPartitioner:
    """fit(hg) -> PartitionResult.

    Levels are coarsened and refined over all executors as tables until the nodes of one fit the driver (dealt) or all of it a single
    task (local); that one and all coarser ones run there, with the same decisions. materialize_neighbors and deferred choose how the distributed levels are coarsened; with
    either, all levels are distributed. deal: whether levels are dealt; by default, those that no task takes by LOCAL_PINS and LOCAL_PAIRS.
    max_levels stops coarsening there."""

    def __init__(self, limits: Limits, passes: int = 1, min_gain: int = 1, admit: str = "not_full", prefix_tie: str = "longest", refine: bool = True, merge: bool = False, materialize_neighbors: bool = False, deferred: int = 0, local_pins: int = LOCAL_PINS, local_pairs: int = LOCAL_PAIRS, max_levels: int | None = None, deal: bool | None = None):
        self.limits, self.passes, self.refine, self.merge, self.max_levels = limits, passes, refine, merge, max_levels
        self.refine_opts = {"admit": admit, "min_gain": min_gain, "prefix_tie": prefix_tie}
        self.coarsen_opts = {"materialize_neighbors": materialize_neighbors, "deferred": deferred}
        self.local_pins, self.local_pairs, self.deal = local_pins, local_pairs, deal

    def _fits(self, hg: Hypergraph) -> bool:
        return not any(self.coarsen_opts.values()) and fits_locally(hg, self.local_pins, self.local_pairs)

    def _deals(self, hg: Hypergraph) -> bool:
        if self.deal is False or any(self.coarsen_opts.values()) or (self.deal is None and fits_locally(hg)):
            return False
        return fits_locally(hg, DEALT_PINS, DEALT_PAIRS) and 0 < hg.nodes.count() <= DEALT_NODES

    def _rest(self, hg: Hypergraph, done: int) -> PartitionResult | None:
        """This level and all coarser ones, if they need not be distributed as tables."""
        return self._local(hg, done) if self._fits(hg) else self._dealt(hg, done) if self._deals(hg) else None

    def _dealt(self, hg: Hypergraph, done: int) -> PartitionResult:
        left = None if self.max_levels is None else self.max_levels - done
        least = hg.edges.agg(F.min("w")).first()[0] or 0
        assign, reports = dealt.Dealt(hg, self.limits, pair_volume(hg)[0]).fit(self.refine, self.passes, left, least, **self.refine_opts)
        return PartitionResult(assign, [(k + done, *rest) for k, *rest in reports][::-1])

    def _local(self, hg: Hypergraph, done: int) -> PartitionResult:
        left = None if self.max_levels is None else self.max_levels - done
        rows = materialize(run_local(hg, self.limits, "multilevel", refine=self.refine, passes=self.passes, max_levels=left, **self.refine_opts), "local")
        reports = rows.filter("kind = 'level'").select("level", "a", "b", "c", "d").orderBy("level").collect()
        return PartitionResult(rows.filter("kind = 'assign'").select(F.col("a").alias("n"), F.col("b").alias("p")), [(r[0] + done, *r[1:]) for r in reports])

    def fit(self, hg: Hypergraph) -> PartitionResult:
        if self.merge:
            hg = merge_parallel(hg)
        if (whole := self._rest(hg, 0)) is not None:
            return whole
        levels = coarsen(hg, self.limits, self.max_levels, until=lambda h: self._fits(h) or self._deals(h), **self.coarsen_opts)
        coarse = self._rest(levels[-1].graph, len(levels) - 1)
        start = coarse and coarse.assign
        if not self.refine:
            return PartitionResult(initial_assignment(levels, start))
        fine = refine(levels, self.limits, self.passes, start, **self.refine_opts)
        return PartitionResult(fine.assign, [*fine.reports, *(coarse.reports if coarse else [])])
