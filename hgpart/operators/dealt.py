"""The whole partitioner with its nodes' arrays in the driver and its pins dealt to tasks: the decisions of `local`, for hypergraphs whose pins
are too many for one task while their nodes are not too many for one array.

Pins lie in written chunks of whole hyperedges, packed as arrays. What is added up over a node's hyperedges (its candidates, its best
partition) is done in blocks of nodes: the task of a block reads all chunks and keeps the hyperedges of its nodes. What belongs to
hyperedges (contraction, savings, events of moves) is done chunk by chunk. No pin, pair or event is left out.
"""

from __future__ import annotations

import contextlib
from collections import defaultdict
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgpart.model import Hypergraph, Limits
from hgpart.operators import local
from hgpart.operators.local import BIG, Graph
from hgpart.plans.checkpoints import forget, materialize

#: Pins of a chunk, and of the nodes of a block.
CHUNK_PINS, BLOCK_PINS = 2_000_000, 3_000_000
_CHUNK = "pins long, n binary, f binary, s binary, w binary, m binary"
#: Chunks go to Python one by one, not thousands of rows at once; blocks, which read with one task each, stay tasks of their own in a union.
_SETTINGS = {"spark.sql.execution.arrow.maxRecordsPerBatch": "1", "spark.sql.unionOutputPartitioning": "false"}


@contextlib.contextmanager
def _chunk_by_chunk(spark: SparkSession):
    before = {k: spark.conf.get(k, None) for k in _SETTINGS}
    for k, v in _SETTINGS.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def _row(e, n, f, w, m) -> pa.RecordBatch:
    """A chunk from pins sorted by hyperedge, all of which have pins."""
    s = np.bincount(e, minlength=len(w)).astype(np.int32)
    held = [x.astype(t, copy=False).tobytes() for x, t in ((n, np.int32), (f, np.uint8), (s, np.int32), (w, np.int64), (m, np.int64))]
    return pa.record_batch({"pins": pa.array([len(n)], pa.int64()), **{c: pa.array([x], pa.binary()) for c, x in zip("nfswm", held)}})


def _arrays(batches):
    """n, f, s, w, m of each chunk."""
    for batch in batches:
        for i in range(batch.num_rows):
            yield [np.frombuffer(batch.column(c)[i].as_buffer(), t) for c, t in zip("nfswm", (np.int32, np.uint8, np.int32, np.int64, np.int64))]


def _graph(n, f, s, w, m, size, bound_on, kind=np.int64) -> Graph:
    return Graph(np.repeat(np.arange(len(s), dtype=kind), s), n.astype(kind, copy=False), f > 1, f % 2 > 0, w, m, size, bound_on)


def _flags(g: Graph) -> np.ndarray:
    return g.src.astype(np.uint8) * 2 + g.dst


def _bounding(f, bound_on) -> np.ndarray:
    return {"in": f % 2 > 0, "out": f > 1, "incident": np.ones(len(f), bool)}[bound_on]


def _of(mask, n, f, s, w, m):
    """The hyperedges that hold a node of the mask, with all their pins."""
    e = np.repeat(np.arange(len(s), dtype=np.int32), s)
    hit = np.zeros(len(s), bool)
    hit[e[mask[n]]] = True
    own = hit[e]
    return n[own], f[own], s[hit], w[hit], m[hit]


def _joined(parts: list, kinds) -> list[np.ndarray]:
    """The parts' arrays end to end; the parts are let go."""
    columns, out = [list(x) for x in zip(*parts)] or [[] for _ in kinds], []
    parts.clear()
    for k, kind in enumerate(kinds):
        out.append(np.concatenate(columns[k]) if columns[k] else np.zeros(0, kind))
        columns[k] = None
    return out


def _sliced(x: np.ndarray, slices: int):
    return [x[k * len(x) // slices : (k + 1) * len(x) // slices] for k in range(slices)]


def _ints(column, kind=np.int64) -> np.ndarray:
    return column.to_numpy().astype(kind, copy=False)


class Dealt:
    """Levels and partitions of one hypergraph. Nodes are positions in their sorted ids."""

    def __init__(self, hg: Hypergraph, limits: Limits, pins: int):
        self.spark, self.limits = hg.pins.sparkSession, limits
        self.tasks = self.spark.sparkContext.defaultParallelism
        nodes = hg.nodes.select("n", "size").toArrow()
        ids = _ints(nodes.column("n"))
        order = np.argsort(ids)
        self.ids, self.size = ids[order], _ints(nodes.column("size"))[order]
        self.pins = pins
        self.chunks = self._packed(hg)

    def _packed(self, hg: Hypergraph) -> DataFrame:
        """Chunks of the finest level."""
        flags = F.col("is_src").cast("bigint") * 2 + F.col("is_dst").cast("bigint")
        rows = hg.pins.select("e", F.col("n").alias("x"), flags.alias("y"), F.lit(False).alias("edge")).unionByName(
            hg.edges.select("e", F.col("w").alias("x"), F.col("mult").cast("bigint").alias("y"), F.lit(True).alias("edge"))
        )
        known = self.spark.sparkContext.broadcast(self.ids)

        def pack(batches):
            parts = [[batch.column(c).to_numpy(zero_copy_only=False) for c in ("edge", "e", "x", "y")] for batch in batches]
            edge, e, x, y = _joined(parts, (bool, np.int64, np.int64, np.int64))
            order = np.argsort(e[edge])
            edge_ids, w, m = (v[edge][order] for v in (e, x, y))
            e, n, f = (v[~edge] for v in (e, x, y))
            if not len(e) or not len(edge_ids):
                return
            at = np.minimum(np.searchsorted(edge_ids, e), len(edge_ids) - 1)
            ok = edge_ids[at] == e
            at, n, f = at[ok], np.searchsorted(known.value, n[ok]), f[ok]
            order, _ = local._runs(at, n)
            at, n, f = at[order], n[order], f[order]
            has = np.bincount(at, minlength=len(edge_ids)) > 0
            if len(at):
                yield _row((np.cumsum(has) - 1)[at], n, f, w[has], m[has])

        wide = max(self.tasks, -(-self.pins // CHUNK_PINS))
        out = materialize(rows.repartition(wide, "e").mapInArrow(pack, _CHUNK), "chunks")
        known.destroy()
        return out

    def _collected(self, df: DataFrame, *shared) -> pa.Table:
        with _chunk_by_chunk(self.spark):
            out = df.toArrow()
        for x in shared:
            x.destroy()
        return out

    def _by_block(self, chunks: DataFrame, pins: int, work, schema: str, shared) -> pa.Table:
        """What work(mask of the block's nodes, batches of all chunks) gives for each block of nodes."""
        N, blocks = len(self.size), max(self.tasks, -(-pins // BLOCK_PINS))

        def block(k):
            def run(batches):
                mask = np.zeros(N, bool)
                mask[k::blocks] = True
                yield from work(mask, batches)

            return chunks.coalesce(1).mapInArrow(run, schema)

        return self._collected(reduce(DataFrame.unionAll, [block(k) for k in range(blocks)]), shared)

    def propose(self, chunks: DataFrame, pins: int, cand: np.ndarray, score: np.ndarray, rows: np.ndarray, told: np.ndarray) -> None:
        """As local.propose, of the nodes in rows."""
        shared = self.spark.sparkContext.broadcast((cand, score, rows, told, self.size))
        most, full, bound_on = self.limits.max_nodes, self.limits.max_inbound, self.limits.bound_on

        def work(mask, batches):
            cand0, score0, rows, told, size = shared.value
            own, deg, parts = mask & rows, np.zeros(len(size), np.int64), []
            for n, f, s, w, m in _arrays(batches):
                b = _bounding(f, bound_on)
                deg += np.bincount(n[b], None if (m == 1).all() else np.repeat(m, s)[b], len(size)).astype(np.int64)
                parts.append(_of(own, n, f, s, w, m))
            g = _graph(*_joined(parts, (np.int32, np.uint8, np.int32, np.int64, np.int64)), size, bound_on, np.int32)
            cand, score = cand0.copy(), score0.copy()
            local.propose(g, most, full, cand, score, own, told, deg)
            # other nodes in rows look at all their pairs in their own block
            at = np.nonzero(((cand != cand0) | (score != score0)) & (own | ~rows))[0]
            yield pa.record_batch({"n": pa.array(at, pa.int64()), "c": pa.array(cand[at], pa.int64()), "score": pa.array(score[at], pa.int64())})

        got = self._by_block(chunks, pins, work, "n long, c long, score long", shared)
        local._take_best(cand, score, *(_ints(got.column(c)) for c in ("n", "c", "score")))

    def contract(self, chunks: DataFrame, gamma: np.ndarray) -> tuple[DataFrame, int]:
        """The chunks, pins mapped and merged, and how many these are."""
        shared = self.spark.sparkContext.broadcast((gamma, self.size, self.limits.bound_on))

        def run(batches):
            gamma, size, bound_on = shared.value
            for n, f, s, w, m in _arrays(batches):
                h = local.contracted(_graph(n, f, s, w, m, size, bound_on), gamma)
                yield _row(h.e, h.n, _flags(h), w, m)

        with _chunk_by_chunk(self.spark):
            out = materialize(chunks.mapInArrow(run, _CHUNK), "chunks")
        shared.destroy()
        return out, int(out.agg(F.sum("pins")).first()[0] or 0)

    def coarsen(self, max_levels: int | None) -> tuple[list[tuple], DataFrame]:
        """[(nodes alive, their sizes, gamma to the next level, pins)], finest first, the last with gamma None; chunks of the last.
        Looks again at what changed only, as local.coarsen does."""
        most, N = self.limits.max_nodes, len(self.size)
        target = -(-int(self.size.sum()) // most) if most < BIG else 1
        alive, ids, finest = np.ones(N, bool), np.arange(N), self.size
        cand, score = np.full(N, -1), np.full(N, -BIG)
        rows, told = alive, np.zeros(N, bool)
        chunks, pins, levels = self.chunks, self.pins, []
        while alive.sum() > target and len(levels) != max_levels:
            self.propose(chunks, pins, cand, score, rows, told)
            mate = local.matching(cand, np.where(cand < 0, 0, score))
            if (mate == ids).all():
                break
            gamma, merged = np.minimum(mate, ids), mate != ids
            levels.append((alive, self.size, gamma.astype(np.int32), pins))
            coarse, pins = self.contract(chunks, gamma)
            if chunks is not self.chunks:
                forget(chunks)
            chunks, size = coarse, np.zeros(N, np.int64)
            np.add.at(size, gamma, self.size)
            self.size = size
            alive = alive & (gamma == ids)
            told = merged & alive
            rows = told | alive & (cand >= 0) & merged[cand]
            cand[merged | rows], score[merged | rows] = -1, -BIG
        levels.append((alive, self.size, None, pins))
        self.size = finest
        return levels, chunks

    def weigh(self, chunks: DataFrame, p: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
        """Saving and total by node, inbound hyperedges by partition, connectivity."""
        shared, slices = self.spark.sparkContext.broadcast((p, self.size, self.limits.bound_on)), self.tasks

        def run(batches):
            p, size, bound_on = shared.value
            sums, cost = np.zeros((3, len(size)), np.int64), 0
            for n, f, s, w, m in _arrays(batches):
                ee, pp, _, cnt_in, saving, total = local.partition_pins(_graph(n, f, s, w, m, size, bound_on), p)
                sums[0] += saving
                sums[1] += total
                np.add.at(sums[2], pp[cnt_in > 0], m[ee[cnt_in > 0]])
                cost += int((w * np.maximum(np.bincount(ee, minlength=len(w)) - 1, 0)).sum())
            for k, x in enumerate(_sliced(sums.T, slices)):
                yield pa.record_batch({"k": pa.array([k], pa.int32()), "x": pa.array([np.ascontiguousarray(x).tobytes()], pa.binary()), "cost": pa.array([0 if k else cost], pa.int64())})

        def add(batches):
            found = defaultdict(lambda: [0, 0])
            for batch in batches:
                for k, x, cost in zip(batch.column("k").to_pylist(), batch.column("x"), batch.column("cost").to_pylist()):
                    found[k][0] = found[k][0] + np.frombuffer(x.as_buffer(), np.int64)
                    found[k][1] += cost
            for k, (x, cost) in found.items():
                yield pa.record_batch({"k": pa.array([k], pa.int32()), "x": pa.array([x.tobytes()], pa.binary()), "cost": pa.array([cost], pa.int64())})

        schema = "k int, x binary, cost long"
        got = self._collected(chunks.mapInArrow(run, schema).repartition(slices, "k").mapInArrow(add, schema), shared)
        by = {k: np.frombuffer(x.as_buffer(), np.int64) for k, x in zip(got.column("k").to_pylist(), got.column("x"))}
        sums = np.concatenate([by[k] for k in sorted(by)]).reshape(-1, 3).T if by else np.zeros((3, len(p)), np.int64)
        return sums[0], sums[1], sums[2], sum(got.column("cost").to_pylist())

    def meet(self, chunks: DataFrame, pins: int, p, want, takes, psize, best, touch) -> None:
        """As local.add_touch, of the nodes in want; psize None: all partitions in takes."""
        shared = self.spark.sparkContext.broadcast((p, want, takes, psize, self.size, self.limits.bound_on))
        most = self.limits.max_nodes

        def work(mask, batches):
            p, want, takes, psize, size, bound_on = shared.value
            own, pins, open_, edges, done = mask & want, [], [], [], 0
            for n, f, s, w, m in _arrays(batches):
                n, f, s, w, m = _of(own, n, f, s, w, m)
                g = _graph(n, f, s, w, m, size, bound_on)
                ee, pp, _, _ = local.partition_pins(g, p, False)
                mine, free = own[g.n], takes[pp]
                pins.append(((g.e[mine] + done), n[mine]))
                open_.append((ee[free] + done, pp[free].astype(np.int32)))
                edges.append((w,))
                done += len(w)
            e, n = _joined(pins, (np.int64, np.int32))
            ee, pp = _joined(open_, (np.int64, np.int32))
            (w,) = _joined(edges, (np.int64,))
            best, touch = np.full(len(size), -1), np.full(len(size), -BIG)
            if len(e):
                local.add_touch(Graph(e, n, e < 0, e < 0, w, w, size, bound_on), p, ee, pp, takes, own, psize, most, best, touch)
            at = np.nonzero(best >= 0)[0]
            yield pa.record_batch({"n": pa.array(at, pa.int64()), "c": pa.array(best[at], pa.int64()), "score": pa.array(touch[at], pa.int64())})

        got = self._by_block(chunks, min(pins, int(want.sum()) * (1 + pins // max(1, len(p)))), work, "n long, c long, score long", shared)
        n = _ints(got.column("n"))
        best[n], touch[n] = _ints(got.column("c")), _ints(got.column("score"))

    def events(self, chunks: DataFrame, p, idx_of, ps, pd, inbound) -> tuple[np.ndarray, np.ndarray]:
        """By move: change of its gain by earlier moves; by move and one more: change of the number of partitions over the inbound limit."""
        shared, slices = self.spark.sparkContext.broadcast((p, idx_of, ps, pd, inbound, self.size, self.limits.bound_on)), self.tasks
        full, M = self.limits.max_inbound, len(ps)
        kinds = {"seq": np.int64, "tp": np.int32, "ti": np.int32, "td": np.int64}

        def run(batches):
            p, idx_of, ps, pd, _, size, bound_on = shared.value
            seq, turns = np.zeros(M, np.int64), []
            for n, f, s, w, m in _arrays(batches):
                g = _graph(*_of(idx_of >= 0, n, f, s, w, m), size, bound_on)
                if len(g.e):
                    turns.append(local.moved_events(g, *local.partition_pins(g, p, False), idx_of, ps, pd, seq, "independent"))
            turns = _joined(turns, (np.int32, np.int32, np.int64))
            for k, x in enumerate(_sliced(seq, slices)):
                mine = turns[0] % slices == k
                held = [x, *(t[mine] for t in turns)]
                yield pa.record_batch({"k": pa.array([k], pa.int32()), **{c: pa.array([v.astype(t, copy=False).tobytes()], pa.binary()) for (c, t), v in zip(kinds.items(), held)}})

        def add(batches):
            inbound, found = shared.value[4], defaultdict(lambda: [0, []])
            for batch in batches:
                for k, *row in zip(batch.column("k").to_pylist(), *(batch.column(c) for c in kinds)):
                    seq, *turns = (np.frombuffer(x.as_buffer(), t) for x, t in zip(row, kinds.values()))
                    found[k][0] = found[k][0] + seq
                    found[k][1].append(turns)
            for k, (seq, turns) in found.items():
                viol = np.zeros(M + 1, np.int64)
                q, i, d = _joined(turns, (np.int32, np.int32, np.int64))
                local.add_flips(viol, inbound, full, q.astype(np.int64), i.astype(np.int64), d)
                at = np.nonzero(viol)[0]
                held = [seq, at[:0], at, viol[at]]
                yield pa.record_batch({"k": pa.array([k], pa.int32()), **{c: pa.array([v.astype(t, copy=False).tobytes()], pa.binary()) for (c, t), v in zip(kinds.items(), held)}})

        schema = "k int, seq binary, tp binary, ti binary, td binary"
        got = self._collected(chunks.mapInArrow(run, schema).repartition(slices, "k").mapInArrow(add, schema), shared)
        by, viol = {}, np.zeros(M + 1, np.int64)
        for k, seq, at, d in zip(got.column("k").to_pylist(), got.column("seq"), got.column("ti"), got.column("td")):
            by[k] = np.frombuffer(seq.as_buffer(), np.int64)
            np.add.at(viol, np.frombuffer(at.as_buffer(), np.int32), np.frombuffer(d.as_buffer(), np.int64))
        return np.concatenate([by[k] for k in sorted(by)]), viol

    def refine_pass(self, chunks: DataFrame, pins: int, p, alive, known, weighed, admit="not_full", min_gain=1, prefix_tie="longest"):
        """As local.refine_pass; weighed: what weigh gives for p."""
        N, most, full = len(self.size), self.limits.max_nodes, self.limits.max_inbound
        saving, total, inbound, _ = weighed
        psize = np.zeros(N, np.int64)
        np.add.at(psize, p[alive], self.size[alive])
        has, best, touch = known
        want = alive & ~has
        if self.weights_from_0:
            want &= saving >= min_gain
        best[want], touch[want] = -1, -BIG
        has |= want
        takes = psize + (self.size[alive].min(initial=BIG >> 1) if admit == "fits" else 1) <= most
        if want.any() and takes[p[alive]].any():
            self.meet(chunks, pins, p, want, takes, psize if admit == "fits" else None, best, touch)
        n2 = np.nonzero(alive & has & (best >= 0))[0]
        gain = saving[n2] - total[n2] + touch[n2]
        ok = gain >= min_gain
        n2, q2, gain = n2[ok], best[n2[ok]], gain[ok]
        if not len(n2):
            return p, 0, 0
        order = np.lexsort((n2, -gain))
        mv, pd, gain = n2[order], q2[order], gain[order]
        ps, M = p[mv], len(mv)
        idx_of = np.full(N, -1)
        idx_of[mv] = np.arange(M)
        change, viol = self.events(chunks, p, idx_of, ps, pd, inbound)
        for load, limit in ((psize, most), (inbound, full)):
            viol[0] += int((load[np.unique(p[alive])] > limit).sum())
        local.add_flips(viol, psize, most, np.concatenate([ps, pd]), np.concatenate([np.arange(M)] * 2), np.concatenate([-self.size[mv], self.size[mv]]))
        return local.best_prefix(p, mv, pd, gain + change, viol, prefix_tie)

    def fit(self, refine=True, passes=1, max_levels=None, least_weight=0, **opts) -> tuple[DataFrame, list[tuple]]:
        """As local.multilevel: (n, p), and the reports."""
        N, self.weights_from_0 = len(self.size), least_weight >= 0
        levels, chunks = self.coarsen(max_levels)
        p, report, cost, finest = np.arange(N), [], None, self.size
        known = (np.zeros(N, bool), np.full(N, -1), np.full(N, -BIG))
        for k in range(len(levels) - 1, -1, -1):
            live, self.size, gamma, pins = levels[k]
            if gamma is not None:
                p = p[gamma]
                known[0][gamma[gamma != np.arange(N)]] = False
                if refine:
                    if chunks is not self.chunks:
                        forget(chunks)
                    at = np.arange(N)
                    for _, _, g, _ in levels[:k]:
                        at = g[at]
                    chunks = self.contract(self.chunks, at)[0] if k else self.chunks
            made = gained = 0
            if refine or cost is None:
                weighed = self.weigh(chunks, p)
                cost = weighed[3]  # a finer level's partitions cost the same
            for i in range((passes or 1 << 30) if refine else 0):
                if i:
                    weighed = self.weigh(chunks, p)
                    cost = weighed[3]
                p, gained, n = self.refine_pass(chunks, pins, p, live, known, weighed, **opts)
                made += n
                cost -= gained  # gains in sequence are what the connectivity falls by
                if not n:
                    break
                known[0][:] = False
            report.append((k, int(live.sum()), pins, int(cost), made))
        self.size = finest
        forget(*{id(x): x for x in (chunks, self.chunks)}.values())
        rows = pa.table({"n": pa.array(self.ids, pa.int64()), "p": pa.array(self.ids[p], pa.int64())})
        return materialize(self.spark.createDataFrame(rows), "assign"), report
