"""The whole partitioner, and the sequential baselines, for hypergraphs that fit one task.

The multi-level part takes the same decisions as the DataFrame steps, with arrays. It serves the upper,
small levels, where a level's dozen of Spark stages would cost far more than its work, and the tests, as a second
implementation. The baselines are sequential by nature.
"""

from __future__ import annotations

import heapq
from collections import defaultdict

import numpy as np

BIG = 1 << 62
#: Pairs, and pins of moved nodes, that the solver adds up at once.
AT_ONCE = 2_000_000
#: Pins of finer levels that wait for their refinement in memory; levels beyond are contracted again from the finest.
KEPT_PINS = 16_000_000


def _runs(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order that sorts by keys (first key first), and where runs of equal keys begin in it."""
    if (packed := _packed(*keys)) is not None:
        order = np.argsort(packed, kind="stable")  # quick where the first key is sorted already
        packed = packed[order]
        return order, np.nonzero(np.concatenate([[True], packed[1:] != packed[:-1]]))[0]
    order = np.lexsort(keys[::-1])
    new = np.zeros(len(order), bool)
    new[:1] = True
    for k in keys:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    return order, np.nonzero(new)[0]


def _packed(*keys: np.ndarray) -> np.ndarray | None:
    """Keys from 0 as one, in the same order; None if there are others, or they do not fit."""
    if not len(keys[0]) or min(k.min() for k in keys) < 0:
        return None
    out, most = keys[0].astype(np.int64), int(keys[0].max())
    for k in keys[1:]:
        width = int(k.max()) + 1
        most = (most + 1) * width
        if most >= BIG:
            return None
        out = out * width + k
    return out


def _sums(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    return np.add.reduceat(values, starts) if len(starts) else values[:0]


def _by_row(pins: np.ndarray, row: np.ndarray) -> np.ndarray:
    """pins (positions) by their row, in place of a slower stable sort."""
    if not len(pins) or int(row.max()) >= 1 << 31 or int(pins.max()) >= 1 << 31:
        return pins[np.argsort(row, kind="stable")]
    packed = (row.astype(np.int64) << 31) | pins
    packed.sort()
    return packed & ((1 << 31) - 1)


def _parts(row: np.ndarray, work: np.ndarray):
    """Slices of pins sorted by row, whole rows of about AT_ONCE work."""
    ends = np.append(np.nonzero(row[1:] != row[:-1])[0] + 1, len(row))
    upto, low, done = np.cumsum(work)[ends - 1] if len(row) else ends, 0, 0
    begin = 0
    while begin < len(row):
        low = max(low + 1, int(np.searchsorted(upto, done + AT_ONCE, "right")))
        yield slice(begin, int(ends[low - 1]))
        begin, done = int(ends[low - 1]), upto[low - 1]


def _meet(begin: np.ndarray, count: np.ndarray) -> np.ndarray:
    """Places of the `count` items from `begin` on, of each list after the other."""
    return np.arange(count.sum()) + np.repeat(begin - (np.cumsum(count) - count), count)


def _pair_sums(row: np.ndarray, col: np.ndarray, width: int, *values: np.ndarray):
    """Distinct (row, col), and the sum of each of values over them."""
    if not len(row):
        return row, col, *values
    low = int(row.min())
    key, most = (row - low).astype(np.int64) * width + col, (int(row.max()) - low + 1) * width
    if most <= 4 * len(key) and all(np.abs(v).sum(dtype=np.float64) < 1 << 53 for v in values):
        at = np.nonzero(np.bincount(key, minlength=most))[0]
        return at // width + low, at % width, *(np.bincount(key, v, most)[at].astype(np.int64) for v in values)
    bits = (len(key) - 1).bit_length()
    if most < BIG >> bits:  # sorts of plain numbers are quickest
        key = (key << bits) | np.arange(len(key))
        key.sort()
        order, key = key & ((1 << bits) - 1), key >> bits
    else:
        order = np.argsort(key)
        key = key[order]
    starts = np.nonzero(np.concatenate([[True], key[1:] != key[:-1]]))[0]
    key = key[starts]
    return key // width + low, key % width, *(_sums(v[order], starts) for v in values)


def _take_best(best: np.ndarray, score: np.ndarray, a: np.ndarray, b: np.ndarray, s: np.ndarray) -> None:
    """Raises best and score of a to the largest (s, b), where that is over what they are."""
    before = score[a]
    np.maximum.at(score, a, s)
    best[a[score[a] > before]] = -1
    hit = s == score[a]
    np.maximum.at(best, a[hit], b[hit])


class Graph:
    """Pins sorted by hyperedge; nodes and hyperedges by position in their sorted ids."""

    def __init__(self, e, n, src, dst, w, mult, size, bound_on="in"):
        if not ((e[1:] > e[:-1]) | ((e[1:] == e[:-1]) & (n[1:] >= n[:-1]))).all():
            order, _ = _runs(e, n)
            e, n, src, dst = e[order], n[order], src[order], dst[order]
        self.e, self.n, self.src, self.dst = e, n, src, dst
        self.w, self.mult, self.size, self.bound_on = w, mult, size, bound_on

    @property
    def bound(self):
        return {"in": self.dst, "out": self.src, "incident": np.ones(len(self.e), bool)}[self.bound_on]

    def held(self, kind):
        """The same with positions of that type: levels wait for their refinement in half the room."""
        if max(len(self.w), len(self.size)) >= 1 << 31:
            return self
        return Graph(self.e.astype(kind), self.n.astype(kind), self.src, self.dst, self.w, self.mult, self.size, self.bound_on)

    def load(self):
        deg = np.zeros(len(self.size), np.int64)
        b = self.bound
        np.add.at(deg, self.n[b], self.mult[self.e[b]])
        return deg


def pair_table(g: Graph):
    """n < m, summed weight, shared bound hyperedges."""
    sizes = np.bincount(g.e, minlength=len(g.w)) if len(g.e) else np.zeros(len(g.w), np.int64)
    first = np.cumsum(sizes) - sizes
    left, right = [], []
    kind = np.int32 if len(g.e) < 1 << 31 else np.int64
    for s in np.unique(sizes[sizes > 1]):
        i, j = (x.astype(kind) for x in np.triu_indices(s, 1))
        base = first[sizes == s].astype(kind)
        for at in range(0, len(base), max(1, 4_000_000 // len(i))):
            part = base[at : at + max(1, 4_000_000 // len(i))]
            left.append((part[:, None] + i).ravel())
            right.append((part[:, None] + j).ravel())
    if not left:
        z = np.zeros(0, np.int64)
        return z, z, z, z
    left, right = np.concatenate(left), np.concatenate(right)
    key = g.n[left] * len(g.size) + g.n[right]
    order = np.argsort(key)
    key = key[order]
    starts = np.nonzero(np.concatenate([[True], key[1:] != key[:-1]]))[0]
    key = key[starts]
    left, right = left[order], right[order]
    del order
    e, b = g.e[left], g.bound
    return key // len(g.size), key % len(g.size), _sums(g.w[e], starts), _sums(np.where(b[left] & b[right], g.mult[e], 0), starts)


def propose(g: Graph, max_nodes: int, max_inbound: int, cand: np.ndarray, score: np.ndarray, rows: np.ndarray | None = None, told: np.ndarray | None = None, deg: np.ndarray | None = None) -> None:
    """Raises cand and score by all pairs, a bounded number at a time, or by those of the nodes in rows; of these, the nodes in told
    are offered to their neighbours too. deg: the nodes' loads, where g lacks some of their hyperedges."""
    sizes = np.bincount(g.e, minlength=len(g.w)) if len(g.e) else np.zeros(len(g.w), np.int64)
    first = np.cumsum(sizes) - sizes
    deg, bound = g.load() if deg is None else deg, g.bound
    pins = np.arange(len(g.e)) if rows is None else np.nonzero(rows[g.n])[0]
    pins = _by_row(pins, g.n[pins])
    e = g.e[pins]
    # all pairs: each once, from its smaller node
    begin, count = (first[e], sizes[e]) if rows is not None else (pins + 1, first[e] + sizes[e] - pins - 1)
    own = g.n[pins]
    for part in _parts(own, count):
        reps = count[part]
        other = _meet(begin[part], reps)
        n, m, hist, shared = _pair_sums(
            np.repeat(own[part], reps), g.n[other], len(g.size), np.repeat(g.w[e[part]], reps), np.repeat(np.where(bound[pins[part]], g.mult[e[part]], 0), reps) * bound[other]
        )
        ok = (n != m) & (g.size[n] + g.size[m] <= max_nodes) & (deg[n] + deg[m] - shared <= max_inbound)
        n, m, hist = n[ok], m[ok], hist[ok]
        _take_best(cand, score, n, m, hist)
        if rows is not None:
            n, m, hist = (x[told[n]] for x in (n, m, hist))
        _take_best(cand, score, m, n, hist)


def proposals(g: Graph, max_nodes: int, max_inbound: int):
    """cand and score by node; cand = -1 where undefined."""
    cand, score = np.full(len(g.size), -1), np.full(len(g.size), -BIG)
    propose(g, max_nodes, max_inbound, cand, score)
    return cand, np.where(cand < 0, 0, score)


def matching(cand: np.ndarray, score: np.ndarray) -> np.ndarray:
    """Mate of each node, itself if none."""
    n = np.nonzero(cand >= 0)[0]
    mate = np.arange(len(cand))
    if not len(n):
        return mate
    order = np.lexsort((n, score[n], cand[n]))
    by = n[order]
    best = by[np.concatenate([cand[by][1:] != cand[by][:-1], [True]])]
    value = np.full(len(cand), -1)  # -1 unknown, else 0 or 1
    value[n] = 0
    value[best] = -1
    value[n[cand[cand[n]] == n]] = 1
    open_ = best[value[best] == -1]
    while len(open_):
        v = value[cand[open_]]
        known = v >= 0
        value[open_[known]] = 1 - v[known]
        open_ = open_[~known]
    hit = np.nonzero(value == 1)[0]
    mate[hit] = cand[hit]
    mate[cand[hit]] = hit
    return mate


def contracted(g: Graph, gamma: np.ndarray) -> Graph:
    n = gamma[g.n]
    order, starts = _runs(g.e, n)
    size = np.zeros_like(g.size)
    np.add.at(size, gamma, g.size)
    either = lambda x: np.logical_or.reduceat(x[order], starts) if len(starts) else x
    return Graph(g.e[order][starts], n[order][starts], either(g.src), either(g.dst), g.w, g.mult, size, g.bound_on)


def connectivity(g: Graph, p: np.ndarray) -> int:
    if not len(g.e):
        return 0
    order, starts = _runs(g.e, p[g.n])
    spans = np.bincount(g.e[order][starts], minlength=len(g.w))
    return int((g.w * np.maximum(spans - 1, 0)).sum())


def coarsen(g: Graph, alive: np.ndarray, max_nodes: int, max_inbound: int, max_levels: int | None = None):
    """[(graph, alive, gamma to the next level)], coarsest last with gamma None; at most max_levels of them have one. Graphs beyond
    KEPT_PINS are None: see level_graph.

    A pair's weight and validity stay as they are while neither node merges. So after a level only merged nodes, and those that
    lost their candidate to a merge, look at all their pairs again; the others look at the merged ones."""
    target = -(-int(g.size.sum()) // max_nodes) if max_nodes < BIG else 1
    levels, kept = [], 0
    cand, score, ids = np.full(len(g.size), -1), np.full(len(g.size), -BIG), np.arange(len(g.size))
    rows = told = None
    while alive.sum() > target and len(levels) != max_levels:
        propose(g, max_nodes, max_inbound, cand, score, rows, told)
        mate = matching(cand, np.where(cand < 0, 0, score))
        if (mate == ids).all():
            break
        gamma, merged = np.minimum(mate, ids), mate != ids
        keep = not levels or kept + len(g.e) <= KEPT_PINS
        kept += len(g.e) * keep
        levels.append((g.held(np.int32) if keep else None, alive, gamma))
        g = contracted(g, gamma)
        alive = alive & (gamma == ids)
        told = merged & alive
        rows = told | alive & (cand >= 0) & merged[cand]
        cand[merged | rows], score[merged | rows] = -1, -BIG
        sizes = np.bincount(g.e, minlength=len(g.w)) if len(g.e) else np.zeros(len(g.w), np.int64)
        if sizes[g.e[rows[g.n]]].sum() > (sizes * (sizes - 1) // 2).sum():
            cand[:], score[:], rows = -1, -BIG, None
    levels.append((g, alive, None))
    return levels


def level_graph(levels: list, k: int) -> Graph:
    """The graph of level k, contracted again from the finest if it was not kept."""
    if (h := levels[k][0]) is not None:
        return h.held(np.int64)
    at = np.arange(len(levels[0][1]))
    for _, _, gamma in levels[:k]:
        at = gamma[at]
    return contracted(levels[0][0], at).held(np.int64)


def partition_pins(g: Graph, p: np.ndarray, sums: bool = True):
    """Hyperedge, partition, pins and bounding pins there, sorted by the first two; with sums, saving and total by node."""
    N = len(g.size)
    order, starts = _runs(g.e, p[g.n])
    ee, pp = g.e[order][starts], p[g.n][order][starts]
    cnt = np.diff(np.concatenate([starts, [len(order)]]))
    cnt_in = _sums(g.bound[order].astype(np.int64), starts)
    if not sums:
        return ee, pp, cnt, cnt_in
    w = g.w[g.e]
    run = np.empty(len(order), np.int64)
    run[order] = np.repeat(np.arange(len(starts)), cnt)
    saving, total = np.zeros(N, np.int64), np.zeros(N, np.int64)
    np.add.at(saving, g.n, np.where(cnt[run] == 1, w, 0))
    np.add.at(total, g.n, w)
    return ee, pp, cnt, cnt_in, saving, total


def add_touch(g: Graph, p, ee, pp, takes, want, psize, max_nodes: int, best, touch) -> None:
    """Raises best and touch of the nodes in want: their pins meet the partitions of their hyperedge (ee, pp) that take a node. psize: only
    partitions that the node fits."""
    N, open_ = len(g.size), takes[pp]
    free = pp[open_]
    spans = np.bincount(ee[open_], minlength=len(g.w))
    begin = np.cumsum(spans) - spans
    pins = np.nonzero(want[g.n] & (spans[g.e] > 0))[0]
    pins = _by_row(pins, g.n[pins])
    own, e = g.n[pins], g.e[pins]
    for part in _parts(own, spans[e]):
        reps = spans[e[part]]
        n2, q2, t2 = _pair_sums(np.repeat(own[part], reps), free[_meet(begin[e[part]], reps)], N, np.repeat(g.w[e[part]], reps))
        ok = q2 != p[n2]
        if psize is not None:
            ok &= psize[q2] + g.size[n2] <= max_nodes
        _take_best(best, touch, n2[ok], q2[ok], t2[ok])


def moved_events(g: Graph, ee, pp, cnt, cnt_in, idx_of, ps, pd, seq, form: str):
    """Adds to seq what earlier moves change of each move's gain. Partition, move and change of its distinct inbound hyperedges where
    these change. idx_of: by node, its move or -1; ps, pd: by move."""
    N = len(g.size)
    kind = np.int32 if N < 1 << 31 else np.int64
    key = ee * N + pp  # sorted

    def running(at, d, values):
        """Of events sorted by hyperedge and partition: values of these at first, and the sum of d up to and with each event."""
        if not len(at):
            return at, d
        first = np.nonzero(np.concatenate([[True], at[1:] != at[:-1]]))[0]
        size = np.diff(np.concatenate([first, [len(at)]]))
        where = np.minimum(np.searchsorted(key, at[first]), len(key) - 1)
        run = np.cumsum(d)
        return np.repeat(np.where(key[where] == at[first], values[where], 0), size), run - np.repeat(run[first] - d[first], size)

    # whole hyperedges at a time
    moved = np.nonzero(idx_of[g.n] >= 0)[0]
    turns = []
    for part in _parts(g.e[moved], np.full(len(moved), 2)):
        mp = moved[part]
        idx, e = idx_of[g.n[mp]], g.e[mp]
        ev_e, ev_p = np.concatenate([e, e]), np.concatenate([ps[idx], pd[idx]])
        ev_i, ev_d = np.concatenate([idx, idx]), np.concatenate([np.full(len(e), -1), np.full(len(e), 1)])
        order, _ = _runs(ev_e - e[0], ev_p, ev_i)
        at = (ev_e * N + ev_p)[order]
        held, run = running(at, ev_d[order], cnt)
        before, k = np.empty(len(order), np.int64), np.empty(len(order), np.int64)
        before[order], k[order] = run - ev_d[order], held
        h = len(e)
        a_s, a_d, ks, kd = before[:h], before[h:], k[:h], k[h:]
        we = g.w[e]
        if form == "independent":
            term = we * ((ks + a_s == 1).astype(np.int64) - (ks == 1) - (kd + a_d == 0) + (kd == 0))
        else:
            plus = ((ks > 1) & (ks + a_s == 1)) | ((kd == 0) & (kd + a_d > 0))
            minus = ((kd > 0) & (kd + a_d == 0)) | ((ks == 1) & (ks + a_s > 1))
            term = we * (plus.astype(np.int64) - minus)
        np.add.at(seq, idx, term)
        # distinct inbound counts after each move
        b = g.bound[mp]
        order = order[np.concatenate([b, b])[order]]
        bd = ev_d[order]
        held, run = running((ev_e * N + ev_p)[order], bd, cnt_in)
        now = held + run
        step = np.where((now > 0) & (now - bd == 0), 1, np.where((now == 0) & (now - bd > 0), -1, 0)) * g.mult[ev_e[order]]
        order, td = order[step != 0], step[step != 0]
        turns.append((ev_p[order].astype(kind), ev_i[order].astype(kind), td))
    return tuple(np.concatenate(x) for x in zip(*turns)) if turns else (np.zeros(0, np.int64),) * 3


def add_flips(viol, load, most: int, q, i, d) -> None:
    """Adds to viol, from the move after i on, where changes d of partitions q by moves i take these over a limit and back."""
    if not len(q):
        return
    order, starts = _runs(q, i)
    q, i, d = q[order][starts], i[order][starts], _sums(d[order], starts)
    head = np.concatenate([[True], q[1:] != q[:-1]])
    run = np.cumsum(d)
    first = np.nonzero(head)[0]
    seg = np.cumsum(head) - 1
    level = load[q] + run - (run[first] - d[first])[seg]
    bad = (level > most).astype(np.int64)
    prev = np.concatenate([[0], bad[:-1]])
    prev[head] = (load[q[head]] > most).astype(np.int64)
    np.add.at(viol, i + 1, bad - prev)


def best_prefix(p, mv, pd, seq, viol, prefix_tie: str):
    """(new partitions, gained, moves made) by the prefix of most gain that ends valid."""
    state, cum = np.cumsum(viol)[1:], np.cumsum(seq)
    ok = (state == 0) & (cum > 0)
    if not ok.any():
        return p, 0, 0
    top = cum[ok].max()
    at = np.nonzero(ok & (cum == top))[0]
    cut = at[-1] if prefix_tie == "longest" else at[0]
    p = p.copy()
    p[mv[: cut + 1]] = pd[: cut + 1]
    return p, int(top), int(cut + 1)


def refine_pass(g: Graph, p: np.ndarray, alive: np.ndarray, max_nodes: int, max_inbound: int, admit="not_full", min_gain=1, prefix_tie="longest", form="independent", known=None):
    """One round of moves: (new partitions, gained, moves made).

    known (mask, partition, touch): by node, whether its best partition is known from a coarser level, and that; filled in."""
    N = len(g.size)
    if not len(g.e):
        return p, 0, 0
    ee, pp, cnt, cnt_in, saving, total = partition_pins(g, p)
    psize = np.zeros(N, np.int64)
    np.add.at(psize, p[alive], g.size[alive])
    # pins meet the partitions of their hyperedge that take a node; no gain is over the saving, as no weight is below 0
    has, best, touch = known if known is not None else (np.zeros(N, bool), np.full(N, -1), np.full(N, -BIG))
    want = alive & ~has
    if not len(g.w) or g.w.min() >= 0:
        want &= saving >= min_gain
    best[want], touch[want] = -1, -BIG
    has |= want
    takes = psize + (g.size[alive].min(initial=BIG >> 1) if admit == "fits" else 1) <= max_nodes
    add_touch(g, p, ee, pp, takes, want, psize if admit == "fits" else None, max_nodes, best, touch)
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
    seq = gain.copy()
    tp, ti, td = moved_events(g, ee, pp, cnt, cnt_in, idx_of, ps, pd, seq, form)
    inbound = np.zeros(N, np.int64)
    has_in = cnt_in > 0
    np.add.at(inbound, pp[has_in], g.mult[ee[has_in]])
    viol = np.zeros(M + 1, np.int64)
    for load, most in ((psize, max_nodes), (inbound, max_inbound)):
        viol[0] += int((load[np.unique(p[alive])] > most).sum())
    add_flips(viol, psize, max_nodes, np.concatenate([ps, pd]), np.concatenate([np.arange(M)] * 2), np.concatenate([-g.size[mv], g.size[mv]]))
    # inbound counts after each move, some partitions at a time
    deals = 1 + len(tp) // AT_ONCE
    for k in range(deals):
        mine = tp % deals == k
        add_flips(viol, inbound, max_inbound, tp[mine].astype(np.int64), ti[mine].astype(np.int64), td[mine])
    p, gained, made = best_prefix(p, mv, pd, seq, viol, prefix_tie)
    return p, gained, made


def multilevel(g: Graph, max_nodes: int, max_inbound: int, refine=True, passes=1, max_levels=None, **opts):
    """(partition by node, [(level, nodes, pins, connectivity after its refinement, moves)])."""
    N = len(g.size)
    alive = np.ones(N, bool)
    levels = coarsen(g, alive, max_nodes, max_inbound, max_levels)
    p = np.arange(N)
    report, cost = [], None
    known = (np.zeros(N, bool), np.full(N, -1), np.full(N, -BIG))
    for k in range(len(levels) - 1, -1, -1):
        h = level_graph(levels, k)
        _, live, gamma = levels.pop()
        if gamma is not None:
            p = p[gamma]
            known[0][gamma[gamma != np.arange(N)]] = False
        made = 0
        if refine:
            for _ in range(passes if passes else 1 << 30):
                p, gained, n = refine_pass(h, p, live, max_nodes, max_inbound, known=known, **opts)
                made += n
                if not n:
                    break
                known[0][:] = False
        if cost is None or made:  # a finer level's partitions cost the same
            cost = connectivity(h, np.where(live, p, 0))
        report.append((k, int(live.sum()), len(h.e), cost, made))
    return p, report


def _sets(g: Graph):
    """Incident hyperedges, and those that bound, of each node."""
    incident, bounding = defaultdict(list), defaultdict(list)
    for e, n, b in zip(g.e.tolist(), g.n.tolist(), g.bound.tolist()):
        incident[n].append(e)
        if b:
            bounding[n].append(e)
    return incident, bounding


def one_pass(g: Graph, max_nodes: int, max_inbound: int) -> np.ndarray:
    """Nodes by id into the open partition; a new one when a limit would break. Named by their first node."""
    _, bounding = _sets(g)
    p, size, held, at = np.zeros(len(g.size), np.int64), 0, set(), -1
    load = 0
    for n in range(len(g.size)):
        new = [e for e in bounding[n] if e not in held]
        more = sum(int(g.mult[e]) for e in new)
        if at < 0 or size + g.size[n] > max_nodes or load + more > max_inbound:
            at, size, held, load = n, 0, set(), 0
            new = bounding[n]
            more = sum(int(g.mult[e]) for e in new)
        held.update(new)
        size, load = size + g.size[n], load + more
        p[n] = at
    return p


def overlap(g: Graph, max_nodes: int, max_inbound: int, fallback: str = "new") -> np.ndarray:
    """Nodes by id into the valid partition with the heaviest shared hyperedges, the later on ties; else a new one
    (or, with fallback="newest", the newest if valid)."""
    incident, bounding = _sets(g)
    touching: dict[int, set[int]] = defaultdict(set)
    size, held, load = {}, {}, {}
    p, newest = np.zeros(len(g.size), np.int64), -1

    def fits(q, n):
        return size[q] + g.size[n] <= max_nodes and load[q] + sum(int(g.mult[e]) for e in bounding[n] if e not in held[q]) <= max_inbound

    for n in range(len(g.size)):
        score: dict[int, int] = defaultdict(int)
        for e in incident[n]:
            for q in touching[e]:
                score[q] += int(g.w[e])
        home = next((q for q in sorted(score, key=lambda q: (score[q], q), reverse=True) if fits(q, n)), None)
        if home is None and fallback == "newest" and newest >= 0 and fits(newest, n):
            home = newest
        if home is None:
            home = newest = n
            size[n], held[n], load[n] = 0, set(), 0
        load[home] += sum(int(g.mult[e]) for e in bounding[n] if e not in held[home])
        held[home].update(bounding[n])
        size[home] += int(g.size[n])
        for e in incident[n]:
            touching[e].add(home)
        p[n] = home
    return p


def _sequential_level(g: Graph, alive: np.ndarray, max_nodes: int, max_inbound: int) -> np.ndarray:
    """Nodes by id, each merged with its best valid free neighbour."""
    n, m, hist, shared = pair_table(g)
    deg = g.load()
    ok = (g.size[n] + g.size[m] <= max_nodes) & (deg[n] + deg[m] - shared <= max_inbound)
    near = defaultdict(list)
    for a, b, s in zip(n[ok].tolist(), m[ok].tolist(), hist[ok].tolist()):
        near[a].append((s, b))
        near[b].append((s, a))
    gamma, free = np.arange(len(g.size)), alive.copy()
    for v in np.nonzero(alive)[0].tolist():
        if free[v]:
            best = max(((s, u) for s, u in near[v] if free[u] and u != v), default=None)
            if best:
                free[v] = free[best[1]] = False
                gamma[v] = gamma[best[1]] = min(v, best[1])
    return gamma


def _sequential_refine(g: Graph, p: np.ndarray, alive: np.ndarray, max_nodes: int, max_inbound: int) -> np.ndarray:
    """Best valid move first among partitions that share a hyperedge with the node, each node once, on through losses
    until no valid move is left, back to the best state.

    Risen gains enter the heap at once; fallen ones when they come up. Moves that do not fit wait for their
    partition to lose a node."""
    incident, _ = _sets(g)
    bound = {(int(e), int(n)) for e, n, b in zip(g.e, g.n, g.bound) if b}
    w, mult, sizes = g.w.tolist(), g.mult.tolist(), g.size.tolist()
    p = p.tolist()
    members: dict[int, list[int]] = defaultdict(list)
    within: dict[tuple[int, int], set[int]] = defaultdict(set)  # (hyperedge, partition) -> its nodes there
    cin, size, load = defaultdict(int), defaultdict(int), defaultdict(int)
    for e, n in zip(g.e.tolist(), g.n.tolist()):
        q = p[n]
        members[e].append(n)
        within[e, q].add(n)
        if (e, n) in bound:
            cin[q, e] += 1
            load[q] += mult[e] if cin[q, e] == 1 else 0
    nodes = np.nonzero(alive)[0].tolist()
    base: dict[int, int] = defaultdict(int)  # saving - total
    touch: dict[int, dict[int, int]] = defaultdict(lambda: defaultdict(int))
    for n in nodes:
        size[p[n]] += sizes[n]
    for (e, q), there in within.items():
        for n in members[e]:
            if p[n] != q:
                touch[n][q] += w[e]
            else:
                base[n] += (w[e] if len(there) == 1 else 0) - w[e]

    def fits(n, q):
        return size[q] + sizes[n] <= max_nodes and load[q] + sum(mult[e] for e in incident[n] if (e, n) in bound and not cin[q, e]) <= max_inbound

    heap = [(-(base[n] + t), n, -q) for n in nodes for q, t in touch[n].items()]
    heapq.heapify(heap)
    locked: set[int] = set()
    waiting: dict[int, set[int]] = defaultdict(set)

    def push(n, q):
        if touch[n][q] > 0:
            heapq.heappush(heap, (-(base[n] + touch[n][q]), n, -q))

    def move(n, q):
        """Moves n and brings the gains of all free nodes up to date."""
        s = p[n]
        for e in incident[n]:
            left, new = within[e, s], within[e, q]
            left.discard(n)
            if not left:
                for m in members[e]:
                    if m not in locked:
                        touch[m][s] -= w[e]
            elif len(left) == 1 and (m := next(iter(left))) not in locked:
                base[m] += w[e]
                for t in touch[m]:
                    push(m, t)
            if not new:
                for m in members[e]:
                    if m not in locked:
                        touch[m][q] += w[e]
                        push(m, q)
            elif len(new) == 1 and (m := next(iter(new))) not in locked:
                base[m] -= w[e]
            new.add(n)
            if (e, n) in bound:
                cin[s, e] -= 1
                load[s] -= mult[e] if not cin[s, e] else 0
                load[q] += mult[e] if not cin[q, e] else 0
                cin[q, e] += 1
        size[s] -= sizes[n]
        size[q] += sizes[n]
        p[n] = q
        for m in waiting.pop(s, ()):
            if m not in locked:
                push(m, s)

    log, total, best, best_at = [], 0, 0, 0
    while heap:
        gain, n, q = heapq.heappop(heap)
        gain, q = -gain, -q
        if n in locked or touch[n][q] <= 0:
            continue
        if base[n] + touch[n][q] != gain:
            if base[n] + touch[n][q] < gain:
                push(n, q)
            continue
        if not fits(n, q):
            waiting[q].add(n)
            continue
        log.append((n, p[n]))
        locked.add(n)
        move(n, q)
        total += gain
        if total > best:
            best, best_at = total, len(log)
    for n, s in reversed(log[best_at:]):
        p[n] = s
    return np.array(p, np.int64)


def sequential(g: Graph, max_nodes: int, max_inbound: int) -> np.ndarray:
    """The sequential multi-level baseline."""
    alive, levels = np.ones(len(g.size), bool), []
    target = -(-int(g.size.sum()) // max_nodes) if max_nodes < BIG else 1
    h = g
    while alive.sum() > target:
        gamma = _sequential_level(h, alive, max_nodes, max_inbound)
        if (gamma == np.arange(len(gamma))).all():
            break
        levels.append((h, alive, gamma))
        h = contracted(h, gamma)
        alive = alive & (gamma == np.arange(len(gamma)))
    p = _sequential_refine(h, np.arange(len(g.size)), alive, max_nodes, max_inbound)
    for h, live, gamma in reversed(levels):
        p = _sequential_refine(h, p[gamma], live, max_nodes, max_inbound)
    return p
