"""SimHash fingerprints and near-duplicate groups by anchor-point covering.

The 64 bits are cut into three segments. Two fingerprints that differ in at most four bits have
two segments, cyclically neighbouring, with at most one differing bit in each, or with none in
the first and at most two in the second (the three counts sum to four at most; any other split
leaves such a pair as well). Anchors are the codewords of the perfect 23-bit three-error-correcting
code, the shorter segments padded with zeros: every value has one anchor within the covering radius three.
A fingerprint lives at the anchor pair of its segments, and is replicated to every anchor pair at
which a fingerprint within the threshold can live. Each anchor pair compares what lives there with
what was replicated there, by exact Hamming distance, so no link is lost and none is guessed.

Copies of a fingerprint are merged before that; the result names components, so links need not be
listed for copies.

Edge cases: a null text has no words and fingerprint zero, like any text without words; a null
doc_id keeps its row, and never serves as component_id unless its whole component has none; repeated rows
stay; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.llm.components import smallest_reachable
from hgpart.llm.tables import written

THRESHOLD = 4
SHINGLE = 4
SEED = 42
#: (first bit, bits) of each segment
SEGMENTS = ((0, 22), (22, 21), (43, 21))
#: Fixed value: generator polynomial of the perfect 23-bit code, x^11 + x^10 + x^6 + x^5 + x^4 + x^2 + 1.
GENERATOR = 0b110001110101


def fingerprint(text: str | None, width: int = SHINGLE) -> int:
    """Majority of the bits of the XXH64 of all word shingles."""
    from xxhash import xxh64_intdigest

    words = (text or "").encode().lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = (ends - lengths).tolist()
    ends = ends.tolist()
    n = max(1, len(words) - width + 1)
    lasts = ends[width - 1 :] if len(words) >= width else ends[-1:]
    hashes = np.fromiter((xxh64_intdigest(joined[a:b], SEED) for a, b in zip(starts, lasts)), np.uint64, n)
    counts = np.zeros(64, np.int64)
    for at in range(0, n, 65536):
        part = hashes[at : at + 65536]
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * counts > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, width: int = SHINGLE) -> DataFrame:
    """doc_id and the fingerprint's 64 bits as a BIGINT, for every row."""

    def run(batches):
        for batch in batches:
            values = np.fromiter((fingerprint(t.as_py(), width) for t in batch.column(1)), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values.view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, fp long")


@lru_cache
def code_tables():
    """(syndromes of the low 12 bits, of the high 11, nearest-codeword error by syndrome)."""

    def rest(x: int) -> int:
        for bit in range(22, 10, -1):
            if x >> bit & 1:
                x ^= GENERATOR << (bit - 11)
        return x

    single = [rest(1 << b) for b in range(23)]

    def all_sums(bits: list[int]) -> np.ndarray:
        out = np.zeros(1, np.int64)
        for s in bits:
            out = np.concatenate([out, out ^ s])
        return out

    low, high = all_sums(single[:12]), all_sums(single[12:])
    leader = np.full(2048, -1, np.int64)
    for error in [0, *(1 << a for a in range(23)), *(1 << a | 1 << b for a in range(23) for b in range(a)), *(1 << a | 1 << b | 1 << c for a in range(23) for b in range(a) for c in range(b))]:
        leader[low[error & 4095] ^ high[error >> 12]] = error
    return low, high, leader


@lru_cache
def reach_tables(bits: int):
    """For each syndrome, the steps from a value to the anchors of all values within one differing
    bit, and of those within two that are not among them; rows are padded with -1."""
    low, high, leader = code_tables()
    syn = lambda e: int(low[e & 4095] ^ high[e >> 12])
    one = [0, *(1 << a for a in range(bits))]
    two = [1 << a | 1 << b for a in range(bits) for b in range(a)]
    near, far = [], []
    for s in range(2048):
        first = {e ^ int(leader[s ^ syn(e)]) for e in one}
        near.append(sorted(first))
        far.append(sorted({e ^ int(leader[s ^ syn(e)]) for e in two} - first))

    def padded(rows):
        out = np.full((len(rows), max(map(len, rows))), -1, np.int64)
        for k, r in enumerate(rows):
            out[k, : len(r)] = r
        return out

    return padded(near), padded(far)


def _segments(fp: np.ndarray):
    """Values, syndromes and home anchors of each segment."""
    low, high, leader = code_tables()
    out = []
    for first, bits in SEGMENTS:
        x = ((fp.view(np.uint64) >> np.uint64(first)) & np.uint64((1 << bits) - 1)).astype(np.int64)
        s = low[x & 4095] ^ high[x >> 12]
        out.append((x, s, x ^ leader[s]))
    return out


def homes(fp: np.ndarray) -> list[np.ndarray]:
    """The anchor pair of each of the three segment pairs, as one key."""
    seg = _segments(fp)
    return [(np.int64(k) << 46) | (seg[k][2] << 23) | seg[(k + 1) % 3][2] for k in range(3)]


def replicas(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, key): every anchor pair at which a fingerprint within the threshold can live."""
    seg, rows, keys = _segments(fp), [], []
    for k in range(3):
        (xa, sa, home), (xb, sb, _) = seg[k], seg[(k + 1) % 3]
        near_a, _ = reach_tables(SEGMENTS[k][1])
        near_b, far_b = reach_tables(SEGMENTS[(k + 1) % 3][1])
        da, db, fb = near_a[sa], near_b[sb], far_b[sb]
        ok = (da >= 0)[:, :, None] & (db >= 0)[:, None, :]
        key = (np.int64(k) << 46) | ((xa[:, None] ^ da)[:, :, None] << 23) | (xb[:, None] ^ db)[:, None, :]
        r, _, _ = np.nonzero(ok)
        rows.append(r)
        keys.append(key[ok])
        ok = fb >= 0
        key = (np.int64(k) << 46) | (home << 23)[:, None] | (xb[:, None] ^ fb)
        rows.append(np.nonzero(ok)[0])
        keys.append(key[ok])
    return np.concatenate(rows), np.concatenate(keys)


def links(distinct: DataFrame) -> DataFrame:
    """(a, b): pairs of different fingerprints with THRESHOLD or fewer differing bits; a pair may come more than once.

    A sort-merge join, so that an anchor with a crowd is spilled and its visitors are split (AQE), not held."""

    def living(batches):
        for batch in batches:
            fp = batch.column(0).to_numpy()
            for at in range(0, len(fp), 65536):
                part = fp[at : at + 65536]
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(homes(part))), pa.array(np.tile(part, 3))], ["anchor", "a"])

    def visiting(batches):
        for batch in batches:
            fp = batch.column(0).to_numpy()
            for at in range(0, len(fp), 4096):
                part = fp[at : at + 4096]
                row, key = replicas(part)
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(part[row])], ["anchor", "b"])

    fp = distinct.select("fp")
    home = fp.mapInArrow(living, "anchor long, a long")
    visit = fp.mapInArrow(visiting, "anchor long, b long")
    close = F.expr(f"bit_count(a ^ b) <= {THRESHOLD} AND a <> b")
    return visit.join(home.hint("merge"), "anchor").filter(close).select("a", "b")


def near_duplicate_groups(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id for every row of docs."""
    rows = written(fingerprints(docs), "fingerprints")
    distinct = rows.groupBy("fp").agg(F.min("doc_id").alias("least_id"))
    distinct = written(distinct, "distinct")
    grouped = smallest_reachable(links(distinct))
    rooted = distinct.join(grouped.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least_id", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("least_id").alias("component_id"))
    named = rooted.select("fp", "root").join(least, "root").select("fp", "component_id")
    return rows.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one_per_group(docs: DataFrame) -> DataFrame:
    """The rows of docs whose doc_id is their component's least: one text of each group stays.

    Rows without doc_id stay too, as nothing can name them; of repeated rows with the kept id all but one go."""
    groups = near_duplicate_groups(docs.select("doc_id", "text"))
    kept = groups.filter(F.col("doc_id") == F.col("component_id")).select("doc_id").distinct()
    named = docs.filter(F.col("doc_id").isNotNull()).join(kept, "doc_id", "left_semi").dropDuplicates(["doc_id"])
    return named.unionByName(docs.filter(F.col("doc_id").isNull())).select(*[F.col(f"`{c}`") for c in docs.columns])
