"""Benchmark decontamination: CGK random walks turn word edits into Hamming distance.

A repetition walks over a window of words: at each step it writes the word under the pointer and
moves on or stays, as a bit derived from word, step and repetition says. Windows a few edits from an
item write mostly the same, so the words at a few sampled steps form a key that both share with good
probability; REPEATS keys, half of them read from the window's end, reach the target recall. Windows are
item-sized and start where the text shares q words with an item; by the q-gram lemma a text within
the allowed edits of an item must share more such grams than a stated count, so this drops nothing.
Windows whose key meets an item's key are verified by the exact edit distance in words between the
item and the best stretch of the text there (bit-parallel). An item matches at distance
(1 - SIMILARITY) * words or less.

The items are held by the driver and by each task one block of BLOCK_BYTES at a time; a larger benchmark is matched block by
block against all texts, each block's matches being written before the next block is read. Where a gram is common
to many items, its places are taken a bounded number at a time.

Case, punctuation and white space do not count. Edge cases: null or empty texts match nothing, an item without
words is ignored, null ids are carried along, repeated rows are reported each, empty tables give empty
results, further columns are ignored.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.llm.tables import written
from hgpart.llm.words import Words, lowered_slices, mixed

SIMILARITY = 0.8
REPEATS = 32
SAMPLED = 3
#: Items are held by each task; more than this many bytes of them are matched block by block.
BLOCK_BYTES = 32 << 20
#: Places of a text times items that share a gram there, taken at once.
MET_AT_ONCE = 1 << 20
#: Steps of a walk that keys may sample; they reach some 70 words. Items of LONG words are walked from their middle too, so that
#: edits at both ends do not hide them.
WALK = 128
LONG = 160


def edit_limit(n_words: int, similarity: float = SIMILARITY) -> int:
    return int((1 - similarity) * n_words + 1e-9)


def best_distance(item: list[int], text: list[int]) -> tuple[int, int]:
    """Least edit distance in words of item to any stretch of text, and where the stretch ends."""
    m = len(item)
    where: dict[int, int] = {}
    for k, w in enumerate(item):
        where[w] = where.get(w, 0) | 1 << k
    full, top = (1 << m) - 1, 1 << (m - 1)
    plus, minus, score = full, 0, m
    best, end = m, 0
    for at, w in enumerate(text):
        eq = where.get(w, 0)
        xv = eq | minus
        xh = (((eq & plus) + plus) ^ plus) | eq
        hp = minus | (full & ~(xh | plus))
        hm = plus & xh
        score += (1 if hp & top else 0) - (1 if hm & top else 0)
        hp, hm = (hp << 1) & full, (hm << 1) & full
        plus = hm | (full & ~(xv | hp))
        minus = hp & xv
        if score < best:
            best, end = score, at + 1
    return best, end


class Index:
    """Items with their grams and their walk keys."""

    def __init__(self, items: list[tuple[int, str]], similarity: float = SIMILARITY, repeats: int = REPEATS, sampled: int = SAMPLED, seed: int = 7):
        words = Words([(t or "").lower().encode() for _, t in items])
        self.ids, self.words, self.limit, self.need, self.size_class = [], [], [], [], []
        grams = defaultdict(list)
        for k, (item_id, _) in enumerate(items):
            w = words.hash[words.first[k] : words.first[k + 1]]
            if not len(w):
                continue
            m, i = len(w), len(self.ids)
            limit = edit_limit(m, similarity)
            q = next(q for q in (3, 2, 1) if m - q + 1 - q * limit >= 1 or q == 1)
            self.ids.append(item_id)
            self.words.append(w)
            self.limit.append(limit)
            self.need.append(max(1, m - q + 1 - q * limit))
            self.size_class.append(int(np.log(m) / np.log(1.25)))
            grams[q].append((i, w))
        self.limit, self.need, self.size_class = (np.array(x, np.int64) for x in (self.limit, self.need, self.size_class))
        self.length = np.array([len(w) for w in self.words], np.int64)
        self.grams = {q: self._gram_table(q, pairs) for q, pairs in grams.items()}
        rng = np.random.default_rng(seed)
        self.repeats, self.sampled = repeats, sampled
        self.turn = rng.integers(1, 1 << 63, (WALK, repeats), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.steps, self.table, self.long = {}, {}, set()
        for c in sorted(set(self.size_class.tolist())):
            members = np.nonzero(self.size_class == c)[0]
            if self.length[members].min() >= LONG:
                self.long.add(c)
            span = max(1, min(WALK, int(1.8 * self.length[members].min())))
            self.steps[c] = np.sort(rng.integers(0, span, (repeats, sampled)), axis=1)
            flat = np.concatenate([self.words[i] for i in members])
            ends = np.cumsum(self.length[members])
            keys = self.keys(flat, ends - self.length[members], ends, ends - self.length[members], ends, c)
            order = np.argsort(keys.ravel(), kind="stable")
            self.table[c] = (keys.ravel()[order], np.tile(members, repeats)[order])

    @staticmethod
    def _gram_table(q, pairs):
        h, item, offset = [], [], []
        for i, w in pairs:
            n = len(w) - q + 1
            g = np.full(n, q, np.uint64)
            for k in range(q):
                g = mixed(g * np.uint64(0x9E3779B97F4A7C15) + w[k : k + n])
            h.append(g)
            item.append(np.full(n, i))
            offset.append(np.arange(n))
        h, item, offset = map(np.concatenate, (h, item, offset))
        order = np.argsort(h, kind="stable")
        seen = np.zeros(1 << 22, bool)
        seen[(h & np.uint64((1 << 22) - 1)).astype(np.int64)] = True
        return h[order], item[order], offset[order], seen

    def keys(self, words, starts, ends, low, high, c):
        """(repeats, windows): walk keys of the windows; walks stay within [low, high)."""
        steps = self.steps[c]
        n, r = len(starts), self.repeats
        middle = (starts + ends) // 2
        begin = np.stack([starts, ends - 1, middle, middle - 1])[np.arange(r) % (4 if c in self.long else 2)]
        way = np.where(np.arange(r) % 2 == 0, 1, -1)[:, None]
        moved = np.zeros((r, n), np.int64)
        key = np.full((r, n), 1, np.uint64) * (np.arange(r, dtype=np.uint64)[:, None] + np.uint64(1 + 1000 * c))
        for j in range(int(steps.max()) + 1):
            at = begin + way * moved
            ok = (at >= low[None, :]) & (at < high[None, :])
            word = np.where(ok, words[np.clip(at, 0, len(words) - 1)], np.uint64(0))
            for k in range(steps.shape[1]):
                hit = steps[:, k] == j
                if hit.any():
                    key[hit] = mixed(key[hit] * np.uint64(0x9E3779B97F4A7C15) + word[hit])
            moved += ((word * self.turn[j][:, None]) >> np.uint64(63)).astype(np.int64)
        return key

    def _met(self, words: Words, q: int):
        """(text and item as one number, place, offset in the item) of each gram of q words that both hold, in parts."""
        table, item, offset, seen = self.grams[q]
        at, h = words.grams(q)
        some = np.nonzero(seen[(h & np.uint64((1 << 22) - 1)).astype(np.int64)])[0]
        at, h = at[some], h[some]
        low = np.searchsorted(table, h, "left")
        count = np.searchsorted(table, h, "right") - low
        at, low, count = at[count > 0], low[count > 0], count[count > 0]
        part = np.cumsum(count) // MET_AT_ONCE
        for bounds in np.split(np.arange(len(at)), np.nonzero(np.diff(part))[0] + 1):
            if len(bounds):
                a, n = at[bounds], count[bounds]
                row = np.repeat(np.arange(len(a)), n)
                entry = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n) + low[bounds][row]
                yield words.text[a[row]] * np.int64(len(self.ids)) + item[entry], a[row], offset[entry]

    def matches(self, words: Words):
        """(text, item, distance, first word, end word) of each item found in each text."""
        starts = defaultdict(set)
        n_items = len(self.ids)
        for q in self.grams:
            # how many places of a text share a gram with an item: a gram that an item holds twice counts once at each place
            counted = [np.unique(np.unique(np.stack([pair, pos]), axis=1)[0], return_counts=True) for pair, pos, _ in self._met(words, q)]
            if not counted:
                continue
            found, where = np.unique(np.concatenate([c[0] for c in counted]), return_inverse=True)
            times = np.bincount(where, np.concatenate([c[1] for c in counted]))
            found = found[times >= self.need[found % n_items]]
            if not len(found):
                continue
            for pair, pos, offset in self._met(words, q):
                mine = np.isin(pair, found)
                # the start may lie before the text's first word; the text is that of the gram itself
                text, item = pair[mine] // n_items, pair[mine] % n_items
                for p, i, t in zip((pos[mine] - offset[mine]).tolist(), item.tolist(), text.tolist()):
                    starts[int(self.size_class[i])].add((p, int(self.length[i]), t))
        best = {}
        for c, windows in starts.items():
            win = np.array(sorted((int(p), int(m), int(t)) for p, m, t in windows), np.int64)
            table, member = self.table[c]
            for at in range(0, len(win), 4096):
                part = win[at : at + 4096]
                low, high = words.first[part[:, 2]], words.first[part[:, 2] + 1]
                keys = self.keys(words.hash, part[:, 0], part[:, 0] + part[:, 1], low, high, c)
                flat = keys.ravel()
                lo, hi = np.searchsorted(table, flat, "left"), np.searchsorted(table, flat, "right")
                hit = np.nonzero(hi > lo)[0]
                pairs = {(int(k % len(part)), int(member[e])) for k in hit for e in range(lo[k], hi[k])}
                for w, i in pairs:
                    p, m, t = part[w]
                    limit = int(self.limit[i])
                    a, b = max(int(low[w]), int(p) - limit), min(int(high[w]), int(p) + int(self.length[i]) + limit)
                    if b <= a:
                        continue
                    d, end = best_distance(self.words[i].tolist(), words.hash[a:b].tolist())
                    if d <= limit and d < best.get((int(t), i), (limit + 1,))[0]:
                        best[int(t), i] = (d, max(a, a + end - int(self.length[i])), a + end)
        return [(t, i, *found) for (t, i), found in best.items()]


def contaminated(docs: DataFrame, benchmark: DataFrame, similarity: float = SIMILARITY, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, item_id, distance (in words), n_words (of the item), first_word, end_word: one row
    for each row of docs and item that its text contains, nearest place."""
    items = benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string"))
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, -(-size // block_bytes))
    schema = "doc_id long, item_id long, distance int, n_words int, first_word int, end_word int"
    found = None
    for block in range(blocks):
        held = [(r[0], r[1]) for r in items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == block).toLocalIterator()]

        def run(batches, held=held):
            index = Index(held, similarity)
            for batch in batches:
                ids = batch.column(0).to_pylist()
                rows = []
                for start, texts in lowered_slices(batch, 1):
                    words = Words(texts)
                    for t, i, d, a, b in index.matches(words):
                        first = int(words.first[t])
                        rows.append((ids[start + t], index.ids[i], d, int(index.length[i]), a - first, b - first))
                columns = list(zip(*rows)) if rows else [[]] * 6
                kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], ["doc_id", "item_id", "distance", "n_words", "first_word", "end_word"])

        part = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, schema)
        if blocks > 1:
            part = written(part, "block")  # so that this block's items can go
        found = part if found is None else found.unionByName(part)
    return found


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without the rows whose doc_id holds a benchmark item; rows without doc_id stay."""
    hits = contaminated(docs.select("doc_id", "text"), benchmark).select("doc_id").distinct()
    return docs.join(hits, "doc_id", "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])
