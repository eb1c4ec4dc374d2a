"""Removal of repeated passages by a hash-compared suffix sort.

A window is a suffix cut at SPAN bytes. Two windows are equal only if their least-hashed k-gram stands at the same
offset, so windows are classed by that anchor: a run of windows with one anchor is a block. Blocks met twice in
whole are repeated; whole blocks are told apart by 128-bit BLAKE2 digests of their bytes. Blocks whose anchor's
k-gram occurs elsewhere but whose content does not are sent, with one copy of each whole block of that k-gram,
to where the k-gram's blocks meet. There the windows at equal offsets are sorted as suffixes: mergesort,
comparing two suffixes by binary search for their common extension over prefix polynomial hashes. Neighbours that
agree over SPAN bytes are verified byte by byte. For a k-gram with more than CROWD different blocks the windows
are dealt by their 128-bit digests, packed by bucket, and met by these instead, so that no task gathers a crowd.

Repeats are handed on as byte ranges of their rows, so what is cut is what was compared.

Edge cases: a null text is empty; texts under SPAN bytes lose nothing and overlap nothing; matches
never cross documents; repeated rows repeat each other; rows are told apart by id and text, so null and repeated
ids do no harm; an empty table gives an empty result; further columns are ignored. Long texts are hashed in
overlapping segments.
"""

from __future__ import annotations

import functools
import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.llm.tables import swept, written
from hgpart.llm.words import mixed, powers

SPAN = 200
GRAM = 40
CROWD = 256
SEGMENT = 1 << 19
#: Windows that a task sorts at once, crowded blocks whose windows it deals out at once, and bytes of texts that it holds beside
#: their batch.
SORTED_WINDOWS = 200_000
CROWD_BLOCKS = 2048
#: Windows of crowds meet in so many buckets at least, and in more so that a bucket gets about SORTED_WINDOWS of them.
LEAST_BUCKETS = 16
SLICE_BYTES = 1 << 20
#: K-grams are met in so many shares, one after another, so that only one share's shuffles are on disk at a time.
SHARES = 4
_WIDTH = SPAN - GRAM + 1
_LOW = np.uint64((1 << 24) - 1)


def _prefix(raw: np.ndarray) -> np.ndarray:
    return np.concatenate([[np.uint64(0)], np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * powers(len(raw) + 1)[0][: len(raw)])])


def digests(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Two columns of BIGINT: the 128-bit digest of each stretch of raw."""
    view = memoryview(raw.tobytes())
    joined = b"".join(hashlib.blake2b(view[a:b], digest_size=16).digest() for a, b in zip(starts.tolist(), ends.tolist()))
    return np.frombuffer(joined, np.int64).reshape(-1, 2)


class Blocks:
    """Blocks of some bytes: first and last window, anchor and gram hash g of each."""

    def __init__(self, raw: np.ndarray, text_starts: np.ndarray, text_ends: np.ndarray):
        self.raw, n = raw, len(raw)
        self.total = _prefix(raw)
        self.down = powers(n + 1)[1]
        grams = self.hash(np.arange(max(0, n - GRAM + 1)), GRAM)
        packed = (grams & ~_LOW) | np.arange(len(grams), dtype=np.uint64)
        least, width = packed, 1
        while 2 * width <= _WIDTH and len(least) > width:
            least = np.minimum(least[:-width], least[width:])
            width *= 2
        rest = _WIDTH - width
        least = np.minimum(least[:-rest], least[rest:]) if len(least) > rest else least[:0]
        ok = np.zeros(len(least) + 1, bool)
        for a, b in zip(text_starts, text_ends):
            if b - a >= SPAN:
                ok[a : b - SPAN + 1] = True
        at = np.nonzero(ok[:-1])[0]
        anchor = (least[at] & _LOW).astype(np.int64)
        new = np.ones(len(at), bool)
        new[1:] = (anchor[1:] != anchor[:-1]) | (at[1:] != at[:-1] + 1)
        self.first = at[new]
        self.last = np.concatenate([at[np.nonzero(new)[0][1:] - 1], at[-1:]]) if len(at) else at
        self.anchor = anchor[new]
        self.g = grams[self.anchor].view(np.int64) if len(at) else np.zeros(0, np.int64)

    def hash(self, start: np.ndarray, size: int) -> np.ndarray:
        return mixed((self.total[start + size] - self.total[start]) * self.down[start])


def _segments(texts: list[bytes]):
    """(row numbers, base in the text, bytes, text starts, text ends): texts together up to SEGMENT bytes; longer ones in overlapping parts."""
    rows, parts, room = [], [], 0

    def lay():
        sizes = np.array([len(p) for _, p in parts], np.int64)
        ends = np.cumsum(sizes)
        return [r for r in rows], [b for b, _ in parts], np.frombuffer(b"".join(p for _, p in parts), np.uint8), ends - sizes, ends

    for row, t in enumerate(texts):
        for base in range(0, max(1, len(t) - SPAN + 1), SEGMENT):
            part = t[base : base + SEGMENT + SPAN - 1]
            if len(part) < SPAN:
                continue
            if parts and room + len(part) > SEGMENT:
                yield lay()
                rows, parts, room = [], [], 0
            rows.append(row)
            parts.append((base, part))
            room += len(part)
    if parts:
        yield lay()


def _bytes(column) -> list[bytes]:
    out = []
    for x in column:
        raw = x.as_buffer() if x.is_valid else None
        out.append(raw.to_pybytes() if raw is not None else b"")
    return out


def _some(texts: list[bytes], most: int = SLICE_BYTES):
    start, room = 0, 0
    for k, t in enumerate(texts):
        if room and room + len(t) > most:
            yield start, texts[start:k]
            start, room = k, 0
        room += len(t)
    if texts:
        yield start, texts[start:]


def common_extension(total: np.ndarray, down: np.ndarray, x: np.ndarray, y: np.ndarray, most: int = SPAN) -> np.ndarray:
    """Bytes that the suffixes at x and y share, at most `most`: binary search over prefix hashes."""
    low, high = np.zeros(len(x), np.int64), np.full(len(x), most)
    for _ in range(int(most).bit_length()):
        mid = (low + high + 1) // 2
        same = (total[x + mid] - total[x]) * down[x] == (total[y + mid] - total[y]) * down[y]
        low, high = np.where(same, mid, low), np.where(same, high, np.maximum(mid - 1, low))
    return low


def sort_suffixes(raw: np.ndarray, starts: np.ndarray, classes: np.ndarray, most: int = SPAN) -> np.ndarray:
    """Order that sorts the suffixes (cut at `most` bytes) within each class: a mergesort over all
    classes at once, in which every element finds its rank in its sibling run by binary search."""
    total, down = _prefix(raw), powers(len(raw) + 1)[1]
    ends = np.concatenate([raw, [0]])
    order = np.argsort(classes, kind="stable")
    n = len(order)
    if n == 0:
        return order
    cls = classes[order]
    head = np.concatenate([[True], cls[1:] != cls[:-1]])
    first = np.nonzero(head)[0]
    size = np.diff(np.concatenate([first, [n]]))
    begin, length = np.repeat(first, size), np.repeat(size, size)
    run = 1
    while run < size.max():
        live = np.nonzero(length > run)[0]
        inside = live - begin[live]
        pair = inside // (2 * run) * (2 * run)
        left = inside - pair < run
        sib = begin[live] + pair + np.where(left, run, 0)
        top = begin[live] + length[live]
        sib, sib_end = np.minimum(sib, top), np.minimum(sib + run, top)
        low, high = sib.copy(), sib_end.copy()
        mine = starts[order[live]]
        for _ in range(run.bit_length() + 1):
            open_ = np.nonzero(low < high)[0]
            if not len(open_):
                break
            mid = (low[open_] + high[open_]) // 2
            x, y = mine[open_], starts[order[mid]]
            ext = common_extension(total, down, x, y, most)
            whole = ext == most
            a, b = ends[np.where(whole, 0, x + ext)], ends[np.where(whole, 0, y + ext)]
            # equal ones keep the left run first
            after = np.where(whole, ~left[open_], b < a)
            low[open_], high[open_] = np.where(after, mid + 1, low[open_]), np.where(after, high[open_], mid)
        rank = low - sib
        place = begin[live] + pair + (inside - pair - np.where(left, 0, run)) + rank
        moved = order.copy()
        moved[place] = order[live]
        order = moved
        run *= 2
    return order


def equal_neighbours(raw: np.ndarray, starts: np.ndarray, classes: np.ndarray, most: int = SPAN) -> np.ndarray:
    """For each suffix whether another of its class shares its `most` bytes, verified byte by byte."""
    order = sort_suffixes(raw, starts, classes, most)
    out = np.zeros(len(starts), bool)
    a, b = order[:-1], order[1:]
    near = np.nonzero(classes[a] == classes[b])[0]
    total, down = _prefix(raw), powers(len(raw) + 1)[1]
    near = near[common_extension(total, down, starts[a[near]], starts[b[near]], most) == most]
    view = np.lib.stride_tricks.sliding_window_view(raw, most) if len(raw) >= most else None
    for at in range(0, len(near), 8192):
        k = near[at : at + 8192]
        k = k[(view[starts[a[k]]] == view[starts[b[k]]]).all(axis=1)]
        out[a[k]] = True
        out[b[k]] = True
    return out


def _keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.xxhash64("doc_id", text).alias("rk"),
        F.coalesce(F.col("doc_id").cast("long"), F.lit(-1)).alias("did"),
        text.cast("binary").alias("raw"),
    )


def _packed(at: np.ndarray, size: np.ndarray, shift: np.ndarray) -> np.ndarray:
    """Where a block stands in its text, its bytes beyond SPAN and its anchor's offset, in one BIGINT."""
    return (at.astype(np.int64) << 20) | ((size - SPAN).astype(np.int64) << 10) | shift.astype(np.int64)


def _unpacked(place: int) -> tuple[int, int, int]:
    return place >> 20, (place >> 10 & 1023) + SPAN, place & 1023


_ANCHORS = "g long, b long, c long, n long, place long, rk long, did long"


def _anchors(batches):
    """A row for each text and different block: n is 2 if the text repeats it. Where it does, all of its places are
    known to repeat, and come merged as rows without g: from b up to c."""
    for batch in batches:
        rk, did, texts = batch.column(0).to_numpy(), batch.column(1).to_numpy(), _bytes(batch.column(2))
        for start, some in _some(texts):
            found, places, grams = [], [], []
            for rows, bases, raw, begins, ends in _segments(some):
                blocks = Blocks(raw, begins, ends)
                part = np.searchsorted(begins, blocks.first, "right") - 1
                size = blocks.last + SPAN - blocks.first
                places.append(_packed(blocks.first - begins[part] + np.array(bases)[part], size, blocks.anchor - blocks.first))
                found.append(np.column_stack([np.array(rows)[part] + start, digests(raw, blocks.first, blocks.last + SPAN)]))
                grams.append(blocks.g)
            if not found:
                continue
            found, place, g = np.concatenate(found), np.concatenate(places), np.concatenate(grams)
            order = np.lexsort((place, found[:, 2], found[:, 1], found[:, 0]))
            found, place, g = found[order], place[order], g[order]
            new = np.concatenate([[True], (found[1:] != found[:-1]).any(axis=1)])
            at = np.nonzero(new)[0]
            count = np.diff(np.concatenate([at, [len(found)]]))
            for k in range(0, len(at), 65536):
                s = at[k : k + 65536]
                yield _anchor_batch(g[s], found[s, 1], found[s, 2], np.minimum(count[k : k + 65536], 2), place[s], rk[found[s, 0]], did[found[s, 0]])
            again = np.nonzero(np.repeat(count > 1, count))[0]
            again = again[np.lexsort((place[again], found[again, 0]))]
            row, low = found[again, 0], place[again] >> 20
            high = low + (place[again] >> 10 & 1023) + SPAN
            merged = []
            for r, a, b in zip(row.tolist(), low.tolist(), high.tolist()):
                if merged and merged[-1][0] == r and a <= merged[-1][2]:
                    merged[-1][2] = max(merged[-1][2], b)
                else:
                    merged.append([r, a, b])
            if merged:
                r, a, b = map(np.array, zip(*merged))
                yield _anchor_batch(None, a, b, np.zeros(len(r), np.int64), np.zeros(len(r), np.int64), rk[r], did[r])


def _anchor_batch(g, b, c, n, place, rk, did):
    g = pa.nulls(len(b), pa.int64()) if g is None else pa.array(g)
    return pa.RecordBatch.from_arrays([g, *(pa.array(x, pa.int64()) for x in (b, c, n, place, rk, did))], ["g", "b", "c", "n", "place", "rk", "did"])


_EDGES = "g long, h long, raw binary, place long, weight long, rk long, did long"


def _edge_blocks(buckets: int):
    """Bytes of the blocks asked for, and the windows of crowded ones by their digests, packed into a row for each of the buckets (h).
    Weight 1: met at this row alone so far; 2: known to repeat; -1: a result."""

    def run(batches):
        for batch in batches:
            rk, did, texts = batch.column(0).to_numpy(), batch.column(1).to_numpy(), _bytes(batch.column(2))
            asked = [list(zip(*x)) for x in zip(*(batch.column(k).to_pylist() for k in (3, 4, 5, 6)))]
            plain, room, crowd = [], 0, []
            for row, wanted in enumerate(asked):
                for place, g, weight, crowded in wanted:
                    at, size, _ = _unpacked(place)
                    block = (g, texts[row][at : at + size], place, weight, row)
                    if crowded:
                        crowd.append(block)
                        if len(crowd) >= CROWD_BLOCKS:
                            yield _crowd_windows(crowd, rk, did, buckets)
                            crowd = []
                        continue
                    plain.append(block)
                    room += size
                    if room > SLICE_BYTES:
                        yield _edge_batch(plain, rk, did)
                        plain, room = [], 0
            if plain:
                yield _edge_batch(plain, rk, did)
            if crowd:
                yield _crowd_windows(crowd, rk, did, buckets)

    return run


def _edge_batch(plain, rk, did):
    g, raw, place, weight, row = zip(*plain)
    row = np.array(row)
    return pa.RecordBatch.from_arrays(
        [pa.array(g, pa.int64()), pa.nulls(len(g), pa.int64()), pa.array(raw, pa.binary()), pa.array(place, pa.int64()), pa.array(weight, pa.int64()), pa.array(rk[row]), pa.array(did[row])],
        ["g", "h", "raw", "place", "weight", "rk", "did"],
    )


def _crowd_windows(crowd, rk, did, buckets):
    """The different windows of these blocks, packed by bucket of their digests, and rows for the outermost of those of a block that others of
    them hold too."""
    _, parts, places, weights, rows = zip(*crowd)
    sizes = np.array([len(x) for x in parts])
    count = sizes - SPAN + 1
    block = np.repeat(np.arange(len(parts)), count)
    inside = np.arange(len(block)) - np.repeat(np.cumsum(count) - count, count)
    start = (np.cumsum(sizes) - sizes)[block] + inside
    both = digests(np.frombuffer(b"".join(parts), np.uint8), start, start + SPAN)
    weight, row, at = np.array(weights)[block], np.array(rows)[block], (np.array(places) >> 20)[block] + inside
    order = np.lexsort((both[:, 1], both[:, 0]))
    new = np.concatenate([[True], (both[order[1:]] != both[order[:-1]]).any(axis=1)])
    group = np.empty(len(order), np.int64)
    group[order] = np.cumsum(new) - 1
    times = np.bincount(group, weight).astype(np.int64)
    known = np.nonzero((times[group] > 1) & (weight == 1))[0]
    known = known[_outermost(block[known])]  # these cover the others of their block
    lead = order[new]
    bucket = both[lead, 0] % buckets
    by = np.argsort(bucket, kind="stable")
    lead, bucket = lead[by], bucket[by]
    windows = np.column_stack([both[lead], at[lead], np.minimum(times[group[lead]], 2), rk[row[lead]], did[row[lead]]])
    first = np.nonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))[0]
    packed = [windows[a:b].tobytes() for a, b in zip(first, [*first[1:], len(lead)])]
    none, zero = pa.nulls(len(known), pa.int64()), np.zeros(len(first), np.int64)
    return pa.RecordBatch.from_arrays(
        [
            pa.nulls(len(known) + len(first), pa.int64()), pa.concat_arrays([none, pa.array(bucket[first])]), pa.array([None] * len(known) + packed, pa.binary()), pa.array(np.concatenate([at[known], zero])),
            pa.array(np.concatenate([np.full(len(known), -1), zero])), pa.array(np.concatenate([rk[row[known]], zero])), pa.array(np.concatenate([did[row[known]], zero])),
        ],
        ["g", "h", "raw", "place", "weight", "rk", "did"],
    )


def _met_windows(batches):
    """Of packed windows, sorted by bucket h, those that repeat and are not yet known to."""
    at_bucket, held = None, []

    def solve():
        windows = np.frombuffer(b"".join(held), np.int64).reshape(-1, 6)
        order = np.lexsort((windows[:, 1], windows[:, 0]))
        key, weight = windows[order, :2], windows[order, 3]
        start = np.nonzero(np.concatenate([[True], (key[1:] != key[:-1]).any(axis=1)]))[0]
        times = np.repeat(np.add.reduceat(weight, start), np.diff([*start, len(order)]))
        hit = windows[order[(times > 1) & (weight == 1)]]
        return pa.RecordBatch.from_arrays([pa.array(hit[:, k]) for k in (2, 4, 5)], ["at", "rk", "did"])

    for batch in batches:
        for bucket, raw in zip(batch.column(0).to_pylist(), _bytes(batch.column(1))):
            if held and bucket != at_bucket:
                yield solve()
                held = []
            at_bucket = bucket
            held.append(raw)
    if held:
        yield solve()


def _outermost(sorted_keys: np.ndarray) -> np.ndarray:
    """Positions of the first and the last of each run of equal keys."""
    if not len(sorted_keys):
        return np.zeros(0, np.int64)
    cut = np.nonzero(np.diff(sorted_keys))[0]
    return np.unique(np.concatenate([[0], cut, cut + 1, [len(sorted_keys) - 1]]))


def _sorted_windows(batches):
    """The windows that blocks of one k-gram share, as byte ranges of the rows whose blocks are single.

    Rows come sorted by g; whole groups are taken together until they are enough for a sort."""
    held: list[pa.RecordBatch] = []
    windows = 0

    def solve(table: pa.Table):
        g, place, weight, rk, did = (table.column(c).to_numpy() for c in ("g", "place", "weight", "rk", "did"))
        raw = table.column("raw").combine_chunks()
        sizes = pc.binary_length(raw).to_numpy()
        raw = np.frombuffer(b"".join(raw.to_pylist()), np.uint8)
        begin = np.cumsum(sizes, dtype=np.int64) - sizes
        count = sizes - SPAN + 1
        block = np.repeat(np.arange(len(sizes)), count)
        inside = np.arange(len(block)) - np.repeat(np.cumsum(count) - count, count)
        group = np.cumsum(np.concatenate([[0], np.diff(g) != 0]))
        classes = group[block] * 512 + ((place & 1023)[block] - inside)
        hit = np.nonzero(equal_neighbours(raw, begin[block] + inside, classes) & (weight[block] == 1))[0]
        hit = hit[_outermost(block[hit])]  # these cover what lies between
        low = (place[block[hit]] >> 20) + inside[hit]
        return pa.RecordBatch.from_arrays([pa.array(low), pa.array(rk[block[hit]]), pa.array(did[block[hit]])], ["at", "rk", "did"])

    for batch in batches:
        for k in range(0, batch.num_rows, 256):
            part = batch.slice(k, 256)
            held.append(part)
            windows += (pc.sum(pc.binary_length(part.column("raw"))).as_py() or 0) - part.num_rows * (SPAN - 1)
            if windows < SORTED_WINDOWS:
                continue
            table = pa.Table.from_batches(held)
            g = table.column("g").to_numpy()
            cut = int(np.searchsorted(g, g[-1], "left"))
            if cut:
                yield solve(table.slice(0, cut))
                held = table.slice(cut).to_batches()
                windows = (pc.sum(pc.binary_length(table.slice(cut).column("raw"))).as_py() or 0) - (len(table) - cut) * (SPAN - 1)
    if held:
        table = pa.Table.from_batches(held)
        if len(table):
            yield solve(table)


def _cutter(with_kept: bool):
    def run(batches):
        for batch in batches:
            ids = batch.column(0)
            places, low, high, single = (batch.column(k).to_pylist() for k in (2, 3, 4, 5))
            for start, some in _some(_bytes(batch.column(1))):
                out = []
                for k, t in enumerate(some, start):
                    spans = [(at, at + size) for at, size, _ in map(_unpacked, places[k] or ())]
                    spans += zip(low[k] or (), high[k] or ())
                    spans += [(at, at + SPAN) for at in single[k] or ()]
                    out.append(_without(t, spans))
                cols = list(zip(*[(len(t), len(t) - len(left), spans, hashlib.sha256(left).hexdigest()) for t, (left, spans) in zip(some, out)]))
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string()]
                arrays, names = [ids.slice(start, len(some)), *(pa.array(c, k) for c, k in zip(cols, kinds))], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
                if with_kept:
                    arrays.append(pa.array([left for left, _ in out], pa.binary()))
                    names.append("kept")
                yield pa.RecordBatch.from_arrays(arrays, names)

    return run


def _without(text: bytes, spans: list[tuple[int, int]]) -> tuple[bytes, int]:
    """text without the spans, and how many there are once merged."""
    merged: list[list[int]] = []
    for a, b in sorted(spans):
        if merged and a <= merged[-1][1]:
            merged[-1][1] = max(merged[-1][1], b)
        else:
            merged.append([a, b])
    kept, at = [], 0
    for a, b in merged:
        kept.append(text[at:a])
        at = b
    return b"".join([*kept, text[at:]]), len(merged)


def _met_blocks(block: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The different blocks whose k-gram stands in two or more blocks, and the places of these."""
    kinds = block.groupBy("g", "b", "c").agg(F.sum("n").alias("n"), F.min(F.struct("did", "rk")).alias("one"))
    grams = kinds.groupBy("g").agg(F.sum("n").alias("all_n"), F.count(F.lit(1)).alias("variants")).filter("all_n > 1")
    shared = swept(written(kinds.join(grams, "g").select("g", "b", "c", "n", "one", "variants"), "shared"))
    met = block.select("g", "b", "c", "place", "rk", "did").join(shared, ["g", "b", "c"])
    return shared, swept(written(met.select("g", "place", "n", "variants", (F.struct("did", "rk") == F.col("one")).alias("leads"), "rk", "did"), "met"))


def remove_repeats(docs: DataFrame, with_kept: bool = True) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, if wanted, kept (the bytes left) for every row of docs."""
    keyed = _keyed(docs)
    anchors = swept(written(keyed.select("rk", "did", "raw").mapInArrow(_anchors, _ANCHORS), "anchors"))
    block = anchors.filter("g is not null")
    shares = [_met_blocks(block.filter(F.pmod("g", F.lit(SHARES)) == k)) for k in range(SHARES)]
    shared, met = (functools.reduce(DataFrame.unionByName, x) for x in zip(*shares))
    whole = F.col("n") > 1
    asked = (F.col("variants") > 1) & (~whole | F.col("leads"))
    flags = met.groupBy("rk", "did").agg(
        F.collect_list(F.when(whole, F.col("place"))).alias("full"),
        F.collect_list(F.when(asked, F.struct("place", "g", F.least("n", F.lit(2)).alias("w"), (F.col("variants") > CROWD).alias("x")))).alias("asked"),
    )
    flags = swept(written(flags, "flags"))
    wanted = flags.filter(F.size("asked") > 0).select("rk", "did", *(F.col(f"asked.{x}").alias(f"a_{x}") for x in ("place", "g", "w", "x")))
    # each block of a crowd is asked for once
    crowds = shared.filter(F.col("variants") > CROWD).count()
    buckets = max(LEAST_BUCKETS, -(-crowds * _WIDTH // SORTED_WINDOWS))
    edges = swept(written(keyed.select("rk", "did", "raw").join(wanted, ["rk", "did"]).mapInArrow(_edge_blocks(buckets), _EDGES), "edges"))
    parts = edges.filter(F.col("raw").isNotNull() & F.col("h").isNull()).drop("h")
    from_sort = parts.repartition("g").sortWithinPartitions("g").mapInArrow(_sorted_windows, "at long, rk long, did long")
    packed = edges.filter(F.col("h").isNotNull()).select("h", "raw")
    from_count = packed.repartition(buckets, "h").sortWithinPartitions("h").mapInArrow(_met_windows, "at long, rk long, did long")
    known = edges.filter(F.col("raw").isNull() & (F.col("weight") < 0)).select(F.col("place").alias("at"), "rk", "did")
    singles = from_sort.unionByName(from_count).unionByName(known).groupBy("rk", "did").agg(F.collect_list("at").alias("single"))
    inside = anchors.filter("g is null").groupBy("rk", "did").agg(F.collect_list(F.struct("b", "c")).alias("inside"))
    marks = flags.filter(F.size("full") > 0).select("rk", "did", "full").join(singles, ["rk", "did"], "full_outer").join(inside, ["rk", "did"], "full_outer")
    marks = swept(written(marks, "marks"))
    return (
        keyed.join(marks, ["rk", "did"], "left")
        .select("doc_id", "raw", "full", F.col("inside.b").alias("low"), F.col("inside.c").alias("high"), "single")
        .mapInArrow(_cutter(with_kept), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * with_kept)
    )


def repeat_report(docs: DataFrame) -> DataFrame:
    return remove_repeats(docs, with_kept=False)
