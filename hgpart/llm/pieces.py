"""SentencePiece encoding and decoding by suffix-array matching.

Texts are cut at blanks into chunks that no piece crosses; each chunk is encoded once and remembered, within
a bound. The chunks of a batch are concatenated and their suffixes sorted; every piece is binary-searched
for its range of occurrences there, and each occurrence is an edge of the chunk. Edges are sorted by
where they end and relaxed in that order: the merge encoding of a prefix has one last piece, namely the one
that starts where a shorter prefix's encoding ends and whose pairing with that prefix's last piece
merging would leave alone. This yields exactly the ids of byte-pair merging by score.

Decoding joins the pieces, turns byte pieces back into bytes and drops the leading blank.

Edge cases: null and empty texts have no ids; characters outside the vocabulary become their bytes; repeated
rows are encoded each; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
BLANK = "▁"
#: Chunks of each of the two generations that a task remembers, and characters it indexes at once.
REMEMBERED = 250_000
INDEXED = 500_000
_LETTERS = re.compile(rf"{BLANK}?[^\W\d_]+|[\W\d_]+")


class Codec:
    def __init__(self, path: str):
        from sentencepiece import sentencepiece_model_pb2 as schema

        model = schema.ModelProto()
        with open(path, "rb") as f:
            model.ParseFromString(f.read())
        if model.trainer_spec.model_type != 2 or model.normalizer_spec.precompiled_charsmap:
            raise ValueError("only byte-pair models without character normalisation are supported")
        pieces = list(model.pieces)
        self.byte_ids = {int(p.piece[3:5], 16): i for i, p in enumerate(pieces) if p.type == 6}
        self.unknown = next(i for i, p in enumerate(pieces) if p.type == 2)
        self.raw = [bytes([int(p.piece[3:5], 16)]) if p.type == 6 else p.piece.replace(BLANK, " ").encode() if p.type == 1 else b"" for p in pieces]
        normal = {p.piece: (i, p.score) for i, p in enumerate(pieces) if p.type == 1}
        self.runs = {len(s): i for s, (i, _) in normal.items() if set(s) == {BLANK}}
        self.longest_run = max(self.runs, default=0)
        chars = sorted(c for c in normal if len(c) == 1)
        merges = sorted((s for s in normal if len(s) > 1 and set(s) != {BLANK}), key=lambda s: (-normal[s][1], normal[s][0]))
        self.dummy = model.normalizer_spec.add_dummy_prefix
        # own numbers: characters first, then merges in the order in which they are made
        self.number = {s: k for k, s in enumerate([*chars, *merges])}
        n = len(self.number)
        self.id_of = np.array([normal[s][0] for s in self.number], np.int32)
        self.left, self.right = np.arange(n), np.arange(n)
        pairs, usable = {}, np.ones(n, bool)
        for s in merges:
            split = self._last_merge(s)
            if split is None:
                usable[self.number[s]] = False
                continue
            a, b = (self.number[x] for x in split)
            self.left[self.number[s]], self.right[self.number[s]] = a, b
            pairs[a * n + b] = self.number[s]
        order = sorted(pairs)
        self.pair_keys = np.array([*order, 1 << 62], np.int64)
        self.pair_merge = np.array([*(pairs[k] for k in order), 0], np.int64)
        self.n = n
        # most pairs never merge: a bit table spares them the search
        self.may_merge = np.zeros(1 << 20, bool)
        self.may_merge[self._slot(self.pair_keys)] = True
        # two bytes a character, so that byte order is the order of suffixes
        self.code = {c: k + 2 for k, c in enumerate(sorted({c for s in self.number for c in s}))}
        self.width = max(map(len, self.number))
        words = sorted(s for s in self.number if usable[self.number[s]])
        self.piece_number = np.array([self.number[s] for s in words])
        self.piece_length = np.array([len(s) for s in words])
        spell = lambda s: b"".join(self.code[c].to_bytes(2, "big") for c in s)
        self.piece_from = np.array([spell(s) for s in words], f"S{2 * self.width}")
        self.piece_to = np.array([spell(s).ljust(2 * self.width, b"\xff") for s in words], f"S{2 * self.width}")
        # where no piece mixes letters with other characters, no merge crosses their seams
        self.seams = all(len(_LETTERS.findall(s)) == 1 for s in self.number)
        self.piece_head = self._slot(np.array([self.code[s[0]] << 16 | self.code[s[1]] if len(s) > 1 else 0 for s in words], np.int64))
        # two generations: what is met again moves to the young one, the old one is dropped when that is full
        self.memo: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def _last_merge(self, s: str):
        parts = list(s)
        while len(parts) > 2:
            ranks = [self.number.get(a + b, 1 << 60) for a, b in zip(parts, parts[1:])]
            best = min(ranks)
            if best == 1 << 60:
                return None
            k = ranks.index(best)
            parts[k : k + 2] = [parts[k] + parts[k + 1]]
        return tuple(parts) if len(parts) == 2 and all(p in self.number for p in parts) else None

    @staticmethod
    def _slot(key: np.ndarray) -> np.ndarray:
        return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(44)).astype(np.int64)

    def stays(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether merging leaves pieces a, b side by side: undoes merges at the seam, latest first,
        and looks for a merge across it that would have come before."""
        a, b = a.copy(), b.copy()
        limit = np.full(len(a), self.n + 1)
        good, alive = np.ones(len(a), bool), np.arange(len(a))
        while len(alive):
            x, y = a[alive], b[alive]
            key = x * self.n + y
            crosses = np.zeros(len(key), bool)
            some = np.nonzero(self.may_merge[self._slot(key)])[0]
            at = np.searchsorted(self.pair_keys, key[some])
            crosses[some] = (self.pair_keys[at] == key[some]) & (self.pair_merge[at] < limit[alive[some]])
            good[alive[crosses]] = False
            alive, x, y = alive[~crosses], x[~crosses], y[~crosses]
            # the later of the two was merged last
            first = x > y
            nx, ny = self.right[x], self.left[y]
            end_x, end_y = nx == x, ny == y
            undo_x = (first & ~end_x) | (~first & end_y & ~end_x)
            undo_y = (~first & ~end_y) | (first & end_x & ~end_y)
            limit[alive] = np.where(undo_x, x, np.where(undo_y, y + 1, limit[alive]))
            a[alive] = np.where(undo_x, nx, x)
            b[alive] = np.where(undo_y, ny, y)
            alive = alive[undo_x | undo_y]
        return good

    def encode_chunks(self, chunks: list[str]) -> None:
        """Remembers the ids of each chunk (characters all of the vocabulary)."""
        lengths = np.array([len(c) for c in chunks])
        text = np.frombuffer("\0".join(chunks).encode("utf-32-le"), np.uint32)
        table = self._codes(int(text.max()) + 1)
        codes = table[text]
        padded = np.concatenate([codes, np.zeros(self.width, np.uint16)]).astype(">u2")
        suffixes = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(padded, self.width)[: len(codes)]).view(f"S{2 * self.width}").ravel()
        order = self._suffix_order(padded[: len(codes) + self.width].astype(np.uint64), len(codes))
        ranked = suffixes[order]
        # only pieces whose first two characters occur are searched
        seen = np.zeros(1 << 20, bool)
        seen[self._slot(codes[:-1].astype(np.int64) << 16 | codes[1:])] = True
        tried = np.nonzero((self.piece_length == 1) | seen[self.piece_head])[0]
        lo, hi = np.searchsorted(ranked, self.piece_from[tried], "left"), np.searchsorted(ranked, self.piece_to[tried], "right")
        count = hi - lo
        which = np.repeat(np.arange(len(count)), count)
        number = tried[which]
        start = order[np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count) + lo[which]]
        piece, end = self.piece_number[number], start + self.piece_length[number]
        chunk_start = np.cumsum(np.concatenate([[0], lengths[:-1] + 1]))
        chunk_of = np.searchsorted(chunk_start, start, "right") - 1
        depth = end - chunk_start[chunk_of]
        by = np.argsort(depth, kind="stable")
        start, end, piece, depth, chunk_of = start[by], end[by], piece[by], depth[by], chunk_of[by]
        last = np.full(len(codes) + 2, -1)
        back = np.zeros(len(codes) + 2, np.int64)
        opening = start == chunk_start[chunk_of]
        bounds = np.searchsorted(depth, np.arange(1, int(lengths.max()) + 2))
        for d in range(len(bounds) - 1):
            e = slice(bounds[d], bounds[d + 1])
            s, t, p, first = start[e], end[e], piece[e], opening[e]
            before = last[s]
            ok = first | (before >= 0)
            check = np.nonzero(ok & ~first)[0]
            ok[check] = self.stays(before[check], p[check])
            last[t[ok]] = p[ok]
            back[t[ok]] = s[ok]
        # walk all chunks back together
        here = chunk_start + lengths
        owner = np.arange(len(chunks))
        got_owner, got_piece = [], []
        while len(here):
            got_owner.append(owner)
            got_piece.append(last[here])
            here = back[here]
            more = here > chunk_start[owner]
            here, owner = here[more], owner[more]
        owner, found = np.concatenate(got_owner[::-1]), np.concatenate(got_piece[::-1])
        by = np.argsort(owner, kind="stable")
        ids = self.id_of[found[by]].tobytes()
        ends = (4 * np.cumsum(np.bincount(owner, minlength=len(chunks)))).tolist()
        self.memo.update(zip(chunks, [ids[a:b] for a, b in zip([0, *ends], ends)]))

    def _suffix_order(self, codes: np.ndarray, n: int) -> np.ndarray:
        """Order of the n suffixes cut at the longest piece: four characters packed, then ranks doubled."""
        m = len(codes) - 3
        key = (codes[:m] << np.uint64(48)) | (codes[1 : m + 1] << np.uint64(32)) | (codes[2 : m + 2] << np.uint64(16)) | codes[3 : m + 3]
        size = 4
        while True:
            order = np.argsort(key)
            ranked = key[order]
            rank = np.empty(len(key), np.uint64)
            rank[order] = np.cumsum(np.concatenate([[False], ranked[1:] != ranked[:-1]])).astype(np.uint64)
            if size >= self.width:
                return order[order < n]
            later = np.zeros(len(rank), np.uint64)
            later[:-size] = rank[size:] + np.uint64(1)
            key = (rank << np.uint64(32)) | later
            size *= 2

    def _codes(self, n: int) -> np.ndarray:
        kept = getattr(self, "_code_table", None)
        if kept is None or len(kept) < n:
            kept = np.ones(n, np.uint16)
            for c, k in self.code.items():
                if ord(c) < n:
                    kept[ord(c)] = k
            self._code_table = kept
        return kept

    def _cut(self, chunk: str) -> list[str]:
        """The chunk cut around characters that no piece holds."""
        out, run = [], []
        for c in chunk:
            if c in self.code:
                run.append(c)
            else:
                if run:
                    out.append("".join(run))
                    run = []
                out.append(c)
        if run:
            out.append("".join(run))
        return out

    def _fallback(self, c: str) -> bytes:
        if not self.byte_ids:
            return np.int32(self.unknown).tobytes()
        return np.array([self.byte_ids[b] for b in c.encode("utf-8", "surrogatepass")], np.int32).tobytes()

    def _remember(self, chunks) -> None:
        memo, known = self.memo, self.code.keys()
        strange = set().union(*chunks) - known
        cuts, plain = {}, set()
        for c in chunks:
            parts = _LETTERS.findall(c) if self.seams else [c]
            if strange and not strange.isdisjoint(c):
                parts = [x for part in parts for x in self._cut(part)]
                plain.update(x for x in parts if x[0] in known)
                cuts[c] = parts
            elif len(parts) > 1:
                plain.update(parts)
                cuts[c] = parts
            else:
                plain.add(c)
        group, room = [], 0
        for c in sorted(self._renewed(plain), key=len):
            if group and room + len(c) > INDEXED:
                self.encode_chunks(group)
                group, room = [], 0
            group.append(c)
            room += len(c) + 1
        if group:
            self.encode_chunks(group)
        for c, parts in cuts.items():
            memo[c] = b"".join([memo[x] if x[0] in known else self._fallback(x) for x in parts])

    def _renewed(self, chunks: set[str]) -> set[str]:
        """Those of chunks that are not remembered; the others are in the young generation afterwards."""
        new = chunks - self.memo.keys()
        if self.old:
            for c in new & self.old.keys():
                self.memo[c] = self.old[c]
            new -= self.memo.keys()
        return new

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text, as little-endian 32-bit integers."""
        split = []
        for t in texts:
            # the n-th blank-separated word carries its blank; empty words are further blanks
            words = (t or "").replace(BLANK, " ").split(" ") if t else []
            split.append([BLANK + w if w else "" for w in words] if self.dummy or not words else [words[0], *(BLANK + w if w else "" for w in words[1:])])
        if len(self.memo) > REMEMBERED:
            self.old, self.memo = self.memo, {}
        new = self._renewed(set().union(*split) - {""})
        if new:
            self._remember(new)
        memo, out = self.memo, []
        single = np.int32(self.runs[1]).tobytes()
        for words in split:
            if "" not in words:
                out.append(b"".join([memo[w] for w in words]))
                continue
            parts, run = [], 0
            for w in words:
                if not w:
                    run += 1
                    continue
                ids = memo[w]
                if run:
                    if ids[:4] == single:  # a blank left alone joins the blanks before it
                        run, ids = run + 1, ids[4:]
                    parts.append(self._blanks(run))
                    run = 0
                parts.append(ids)
            if run:
                parts.append(self._blanks(run))
            out.append(b"".join(parts))
        return out

    def _blanks(self, n: int) -> bytes:
        full, rest = divmod(n, self.longest_run)
        ids = [self.runs[self.longest_run]] * full
        while rest:
            size = max(k for k in self.runs if k <= rest)
            ids.append(self.runs[size])
            rest -= size
        return np.array(ids, np.int32).tobytes()

    def decode(self, ids: bytes) -> str:
        raw = self.raw
        text = b"".join(map(raw.__getitem__, np.frombuffer(ids, np.int32).tolist()))
        if self.dummy and text[:1] == b" ":
            text = text[1:]
        return text.decode("utf-8", "replace")


@lru_cache(maxsize=2)
def codec(path: str = DEFAULT_MODEL) -> Codec:
    return Codec(path)


def _slices(batch: pa.RecordBatch, column: int, most: int = 2 << 20):
    texts, start, room = [], 0, 0
    for row, text in enumerate(batch.column(column)):
        t = text.as_py()
        if texts and room + len(t or "") > most:
            yield start, texts
            texts, start, room = [], row, 0
        texts.append(t)
        room += len(t or "")
    if texts:
        yield start, texts


def encoded(docs: DataFrame, model: str = DEFAULT_MODEL) -> DataFrame:
    """doc_id, ids ARRAY<INT> for every row."""

    def run(batches):
        c = codec(model)
        for batch in batches:
            for start, texts in _slices(batch, 1):
                ids = [np.frombuffer(x, np.int32) for x in c.encode(texts)]
                offsets = np.cumsum([0, *map(len, ids)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(ids) if ids else [], pa.int32()))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(start, len(texts)), lists], ["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, ids array<int>")


def decoded(ids: DataFrame, model: str = DEFAULT_MODEL) -> DataFrame:
    """doc_id, text of rows of doc_id, ids."""

    def run(batches):
        c = codec(model)
        for batch in batches:
            texts = [c.decode(np.array(x.as_py() or [], np.int32).tobytes()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return ids.select(F.col("doc_id").cast("long"), "ids").mapInArrow(run, "doc_id long, text string")


def token_digests(docs: DataFrame, model: str = DEFAULT_MODEL) -> DataFrame:
    """doc_id, n_tokens, ids_crc32 (of the ids as little-endian 32-bit integers), round_trip (decoding
    gives the text back; blanks written as the blank mark do not) for every row."""

    def run(batches):
        c = codec(model)
        for batch in batches:
            for start, texts in _slices(batch, 1):
                ids = c.encode(texts)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(start, len(texts)),
                        pa.array([len(x) // 4 for x in ids], pa.int64()),
                        pa.array([zlib.crc32(x) for x in ids], pa.int64()),
                        pa.array([c.decode(x) == (t or "") for x, t in zip(ids, texts)], pa.bool_()),
                    ],
                    ["doc_id", "n_tokens", "ids_crc32", "round_trip"],
                )

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_tokens long, ids_crc32 long, round_trip boolean")
