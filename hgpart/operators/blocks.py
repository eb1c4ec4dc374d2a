"""Sums over pairs of node and column, and each node's best column, block by block of nodes.

A pair (node, column) weighs what the hyperedges weigh that hold both; columns are other nodes or partitions. There are far more
pairs than pins where hyperedges are large, so none are written or shuffled: nodes are dealt to blocks of bounded work, a block gets its
own pins and the columns of its hyperedges once each, and adds up there. No column is left out, and sums are exact.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hgpart.model import Hypergraph
from hgpart.plans.checkpoints import forget, materialize, small

#: Pairs of a block, at least and at most, and about how many blocks there are between.
LEAST_WORK, MOST_WORK, BLOCKS = 2_000_000, 32_000_000, 256
#: Blocks side by side are joined while they have at most so many pairs and columns: the columns that they share then go to one task once.
JOINED_WORK, JOINED_COLUMNS = 1 << 30, 8_000_000
#: Pairs that a task adds up at once.
PAIRS_AT_ONCE = 4_000_000
#: Sums are held as float64, exact below this.
EXACT = 1 << 53
#: Hyperedges with so many columns are added row by row of the table, smaller ones all together.
WIDE = 256
#: Rows of so many pairs are added up one by one.
LONG = 1024


def take(hg: Hypergraph) -> bool:
    """Whether weights, sizes and ids are in the range that blocks add up exactly."""
    least, total, mult = hg.edges.agg(F.min("w"), F.sum("w"), F.sum("mult")).first()
    low, high, size = hg.nodes.agg(F.min("n"), F.max("n"), F.sum("size")).first()
    return least is None or low is None or (least > 0 and total < EXACT and mult < 1 << 31 and size < 1 << 31 and low >= 0 and high < 1 << 62)


def node_blocks(left: DataFrame, right: DataFrame, least: int = LEAST_WORK, most: int = MOST_WORK) -> tuple[DataFrame, DataFrame, int, int]:
    """(n, block), (e, s) the columns of hyperedges, all pairs and those of a block: nodes by their largest hyperedge, cut where the pairs of a block reach a bound."""
    sizes = materialize(right.groupBy("e").agg(F.count(F.lit(1)).alias("s")), "sizes")
    home = F.max(F.struct("s", "e")).getField("e").alias("home")
    per = left.select("e", "n").join(small(sizes), "e").groupBy("n").agg(F.sum("s").alias("work"), home)
    # the partition number must not change on retries
    ranged = materialize(per.repartitionByRange("home", "n").withColumn("r", F.spark_partition_id()), "ranged")
    total = ranged.agg(F.sum("work")).first()[0] or 0
    width = min(max(least, total // BLOCKS), most)
    before = F.sum("work").over(Window.partitionBy("r").orderBy("home", "n").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    blocks = materialize(ranged.select("n", (F.col("r").cast("bigint") * (1 << 40) + F.floor((before - 1) / F.lit(width))).alias("block")), "blocks")
    forget(ranged)
    return blocks, sizes, int(total), int(width)


def _every(block: str, bits: int):
    """One number for 2 ** bits blocks side by side."""
    return F.expr(f"shiftleft(shiftright({block}, 40), 40) | shiftright({block} & {(1 << 40) - 1}L, {bits})")


def joined_bits(asked: DataFrame, sizes: DataFrame, total: int, width: int) -> int:
    """How often blocks can be joined two by two. asked (at, h): blocks and their hyperedges; sizes (e, s)."""
    tasks = 2 * sizes.sparkSession.sparkContext.defaultParallelism
    sizes = small(sizes).withColumnRenamed("e", "h")
    bits = max(0, (min(JOINED_WORK, total // tasks) // width).bit_length() - 1)
    while bits:
        columns = asked.select(_every("at", bits).alias("at"), "h").distinct().join(sizes, "h").groupBy("at").agg(F.sum("s").alias("s")).agg(F.max("s")).first()[0]
        if (columns or 0) <= JOINED_COLUMNS:
            break
        bits -= 1
    return bits


def best_columns(left: DataFrame, right: DataFrame, edges: DataFrame, solve, least: int = LEAST_WORK, most: int = MOST_WORK) -> DataFrame:
    """(n, c, score), written: for each node what `solve` takes of its columns; no row if none.

    left (e, n, a, b, f) and right (e, c, a, b, f): pins and columns of hyperedges; a and b from 0 below 2 ** 31 on the right,
    f true or false there. solve: see Block.best."""
    blocks, sizes, total, width = node_blocks(left, right, least, most)
    pins = materialize(left.join(small(blocks), "n").select("block", "e", "n", "a", "b", "f"), "block-pins")
    own = pins
    lists = right.groupBy("e").agg(
        F.collect_list(F.expr("shiftleft(c, 1) | cast(f as bigint)")).alias("cs"), F.collect_list(F.expr("shiftleft(cast(a as bigint), 32) | cast(b as bigint)")).alias("ab")
    )
    asked = pins.select(F.col("block").alias("at"), F.col("e").alias("h")).distinct()
    if bits := joined_bits(asked, sizes, total, width):
        pins = pins.withColumn("block", _every("block", bits))
        asked = pins.select(F.col("block").alias("at"), F.col("e").alias("h")).distinct()
    columns = asked.join(lists.join(small(edges).select("e", "w", "mult"), "e").withColumnRenamed("e", "h"), "h").select("at", "h", "w", "mult", "cs", "ab")

    wide, at_once, long = WIDE, PAIRS_AT_ONCE, LONG

    def run(own: pa.Table, held: pa.Table) -> pa.Table:
        n, c, score = solve(Block(own, held, wide, at_once, long)) if own.num_rows and held.num_rows else (np.zeros(0, np.int64),) * 3
        return pa.table({"n": pa.array(n, pa.int64()), "c": pa.array(c, pa.int64()), "score": pa.array(score, pa.int64())})

    best = materialize(pins.groupBy("block").cogroup(columns.groupBy("at")).applyInArrow(run, "n long, c long, score long"), "best")
    forget(own, blocks, sizes)
    return best


def _flat(table: pa.Table, name: str) -> tuple[np.ndarray, np.ndarray]:
    """All items of a list column, and how many each row has."""
    parts = table.column(name).chunks
    items = np.concatenate([p.flatten().to_numpy(zero_copy_only=False) for p in parts])
    return items, np.concatenate([np.diff(p.offsets.to_numpy()) for p in parts])


class Block:
    def __init__(self, own: pa.Table, held: pa.Table, wide: int, at_once: int, long: int):
        self.wide, self.at_once, self.long, self.room = wide, at_once, long, {}
        ids = held.column("h").to_numpy()
        e = own.column("e").to_numpy()
        known = np.isin(e, ids)  # others have no column
        e, n, a, b, f = (own.column(k).to_numpy()[known] for k in ("e", "n", "a", "b", "f"))
        coded, self.size = _flat(held, "cs")
        ab, _ = _flat(held, "ab")
        self.begin = np.cumsum(self.size) - self.size
        self.w, self.mult = (held.column(k).to_numpy().astype(np.float64) for k in ("w", "mult"))
        # columns by falling id, so that the first of equal ones is the largest
        values, first, place = np.unique(-(coded >> 1), return_index=True, return_inverse=True)
        self.ids, self.col, self.col_f = -values, place, (coded & 1).astype(bool)
        self.col_a, self.col_b = ab[first] >> 32, ab[first] & 0xFFFFFFFF
        order = np.argsort(ids)
        edge = order[np.searchsorted(ids, e, sorter=order)]
        # rows by their largest hyperedge, so that those added up together share columns
        self.n, first, row = np.unique(n, return_index=True, return_inverse=True)
        widest = np.lexsort((edge, self.size[edge], row))
        last = np.concatenate([row[widest][1:] != row[widest][:-1], [True]])
        by = np.argsort(edge[widest][last], kind="stable")
        rank = np.empty(len(by), np.int64)
        rank[by] = np.arange(len(by))
        self.n, first, row = self.n[by], first[by], rank[row]
        self.a, self.b, self.f = a[first], b[first], f[first]
        order = np.argsort(row, kind="stable")
        self.row, self.edge, self.pin_f = row[order], edge[order], f[order].astype(bool)
        self.alike = bool((self.w == self.mult).all() and self.col_f.all() and self.pin_f.all())

    def parts(self, both: bool):
        """(rows, columns, sums, sums of mult over what both sides are marked for): a part's rows at a time, as a table of (rows, columns)
        or, where that would be mostly empty, as lists of pairs (then rows and columns are as long as the sums)."""
        lens = self.size[self.edge]
        upto = np.cumsum(np.bincount(self.row, lens, minlength=len(self.n))).astype(np.int64)
        start = np.searchsorted(self.row, np.arange(len(self.n) + 1))
        low = 0
        while low < len(self.n):
            done = upto[low - 1] if low else 0
            high = max(low + 1, int(np.searchsorted(upto, done + self.at_once, "right")))
            pins = slice(start[low], start[high])
            yield self._part(low, high, self.row[pins] - low, self.edge[pins], self.pin_f[pins], int(upto[high - 1] - done), both)
            low = high

    def _pairs(self, row, edge, f, both):
        """Row, column, weight and shared mult of each pair of these pins."""
        lens = self.size[edge]
        at = np.arange(lens.sum()) + np.repeat(self.begin[edge] - (np.cumsum(lens) - lens), lens)
        shared = np.where(self.col_f[at], np.repeat(self.mult[edge] * f, lens), 0) if both else None
        return np.repeat(row, lens), self.col[at], np.repeat(self.w[edge], lens), shared

    def _table(self, name: str, R: int, C: int) -> np.ndarray:
        """A table in room that all parts use one after another."""
        if len(self.room.get(name, ())) < R * C:
            self.room[name] = np.empty(R * C)
        return self.room[name][: R * C].reshape(R, C)

    def _rows(self, low, high, row, edge, f, both):
        """A part added up row by row, for rows that hold so many pairs that these are best counted at once."""
        R, (edges, at) = high - low, np.unique(edge, return_inverse=True)
        spans = [self.col[self.begin[k] : self.begin[k] + self.size[k]] for k in edges]
        if (width := len(self.ids)) * R > 2 * self.size[edge].sum():
            mark = np.zeros(width, bool)
            for span in spans:
                mark[span] = True
            cols = np.nonzero(mark)[0]
            place = np.cumsum(mark) - 1
            spans = [place[span] for span in spans]
        else:
            cols = np.arange(width)
        C = len(cols)
        if both:
            marked = [span[self.col_f[self.begin[k] : self.begin[k] + self.size[k]]] for k, span in zip(edges, spans)]
        starts = np.searchsorted(row, np.arange(R + 1))

        def add(lists, values):
            if not lists:
                return 0
            items = np.concatenate(lists)
            if (values == values[0]).all():
                return np.bincount(items, minlength=C) * values[0]
            return np.bincount(items, np.repeat(values, [len(x) for x in lists]), C)

        sums = self._table("sums", R, C)
        shared = self._table("shared", R, C) if both else sums
        for r in range(R):
            own = slice(starts[r], starts[r + 1])
            sums[r] = add([spans[k] for k in at[own]], self.w[edge[own]])
            if both:
                held = f[own]
                shared[r] = add([marked[k] for k in at[own][held]], self.mult[edge[own][held]])
        return np.arange(low, high), cols, sums, shared

    def _part(self, low, high, row, edge, f, pairs, both):
        if pairs >= self.long * (high - low):
            return self._rows(low, high, row, edge, f, both and not self.alike)
        narrow, wide = self.size[edge] < self.wide, np.unique(edge[self.size[edge] >= self.wide])
        spans = [self.col[self.begin[k] : self.begin[k] + self.size[k]] for k in wide]
        both = both and not self.alike
        r, c, w, s = self._pairs(row[narrow], edge[narrow], f[narrow], both)
        mark = np.zeros(len(self.ids), bool)
        mark[c] = True
        for span in spans:
            mark[span] = True
        cols = np.nonzero(mark)[0]
        place = np.cumsum(mark) - 1
        R, C = high - low, len(cols)
        if R * C > 4 * pairs:
            if len(wide):
                r, c, w, s = self._pairs(row, edge, f, both)
            key = r * C + place[c]
            bits = (len(key) - 1).bit_length() if len(key) else 0
            if R * C < 1 << (62 - bits):  # sorts of plain numbers are quickest
                key = (key << bits) | np.arange(len(key))
                key.sort()
                order, key = key & ((1 << bits) - 1), key >> bits
            else:
                order = np.argsort(key, kind="stable")
                key = key[order]
            at = np.nonzero(np.concatenate([[True], key[1:] != key[:-1]]))[0]
            sums = np.add.reduceat(w[order], at)
            return low + key[at] // C, cols[key[at] % C], sums, np.add.reduceat(s[order], at) if both else sums
        key = r * C + place[c]
        sums = np.bincount(key, w, R * C).astype(np.float64).reshape(R, C)
        shared = np.bincount(key, s, R * C).astype(np.float64).reshape(R, C) if both else sums
        order = np.argsort(edge, kind="stable")
        starts, ends = np.searchsorted(edge[order], wide), np.searchsorted(edge[order], wide, "right")
        for k, a, b, span in zip(wide, starts, ends, spans):
            r, c = row[order[a:b]], place[span]
            sums[r[:, None], c] += self.w[k]
            if both:
                r, c = r[f[order[a:b]]], c[self.col_f[self.begin[k] : self.begin[k] + self.size[k]]]
                shared[r[:, None], c] += self.mult[k]
        return np.arange(low, high), cols, sums, shared

    def best(self, own: np.ndarray, valid, both: bool, tries: int = 2) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """n, column id and sum of the column with the largest (sum, id) of each row that is not own (by row) and of which valid(rows, columns,
        sums, shared) holds. Columns that share no hyperedge with a row are not looked at; weights are over 0."""
        out = []
        place = np.searchsorted(-self.ids, -own)
        place = np.where(self.ids[np.minimum(place, len(self.ids) - 1)] == own, np.minimum(place, len(self.ids) - 1), -1)
        for rows, cols, sums, shared in self.parts(both):
            if sums.ndim == 1:
                ok = (cols != place[rows]) & valid(rows, cols, sums, shared)
                r, c, s = rows[ok], cols[ok], sums[ok]
                order = np.lexsort((-c, s, r))
                last = order[np.concatenate([r[order][1:] != r[order][:-1], [True]])] if len(order) else order
                out.append((r[last], c[last], s[last]))
                continue
            here = np.searchsorted(cols, place[rows])
            hit = (place[rows] >= 0) & (cols[np.minimum(here, len(cols) - 1)] == place[rows])
            sums[np.nonzero(hit)[0], here[hit]] = 0
            left = np.arange(len(rows))
            for _ in range(tries):
                at = sums[left].argmax(1) if len(left) < len(rows) else sums.argmax(1)
                s = sums[left, at]
                left, at, s = left[s > 0], at[s > 0], s[s > 0]
                ok = valid(rows[left], cols[at], s, shared[left, at])
                out.append((rows[left[ok]], cols[at[ok]], s[ok]))
                sums[left[~ok], at[~ok]] = 0
                left = left[~ok]
                if not len(left):
                    break
            step = max(1, self.at_once // 16 // max(1, len(cols)))
            for some in (left[k : k + step] for k in range(0, len(left), step)):
                fit = np.where(valid(rows[some][:, None], cols[None, :], sums[some], shared[some]), sums[some], 0)
                at = fit.argmax(1)
                s = fit[np.arange(len(some)), at]
                out.append((rows[some[s > 0]], cols[at[s > 0]], s[s > 0]))
        r, c, s = (np.concatenate(x) for x in zip(*out)) if out else (np.zeros(0, np.int64),) * 3
        return self.n[r], self.ids[c], np.rint(s).astype(np.int64)
