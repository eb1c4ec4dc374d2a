"""Exact length histogram of encoded documents, and what suffix sums over it answer.

Every whole text is encoded; tasks hand on one row per distinct length. With documents and tokens
counted at or above each length, a context limit L is answered exactly: tokens kept when each
document is cut at L are (tokens of shorter documents) + L * (documents of length L or more).

Edge cases: null and empty texts have length 0, repeated rows count each, an empty table gives
an empty histogram, further columns are ignored. Special-token strings are ordinary text.
"""

from __future__ import annotations

import base64
from collections import Counter

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hgpart.llm.tables import written

DEFAULT_VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: Fixed value: the pattern that splits text before merging.
SPLIT_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Lengths are summed in blocks of this many, so that no task ranks all lengths.
BLOCK = 512


def load_encoding(path: str):
    import tiktoken

    with open(path, "rb") as lines:
        ranks = {base64.b64decode(piece): int(rank) for piece, rank in map(bytes.split, lines)}
    return tiktoken.Encoding("ranks", pat_str=SPLIT_PATTERN, mergeable_ranks=ranks, special_tokens={})


def length_histogram(docs: DataFrame, vocabulary: str = DEFAULT_VOCABULARY, column: str = "text") -> DataFrame:
    """n_tokens, n_docs: how many rows of docs encode to each length."""

    def count(batches):
        encoding, found = load_encoding(vocabulary), Counter()
        for batch in batches:
            for text in batch.column(0):
                found[len(encoding.encode_ordinary(text.as_py() or ""))] += 1
        lengths = sorted(found)
        yield pa.RecordBatch.from_arrays(
            [pa.array(lengths, pa.int64()), pa.array([found[n] for n in lengths], pa.int64())], ["n_tokens", "n_docs"]
        )

    partial = docs.select(F.col(column).cast("string").alias("text")).mapInArrow(count, "n_tokens long, n_docs long")
    return partial.groupBy("n_tokens").agg(F.sum("n_docs").alias("n_docs"))


def suffix_sums(histogram: DataFrame, block: int = BLOCK) -> DataFrame:
    """The histogram with docs_at_least, tokens_at_least, truncated_total (all documents cut at
    n_tokens), docs_cut (longer than n_tokens) and docs_below: two-level sums over blocks of lengths.

    The histogram is written first: it is read several times and costly to make."""
    histogram = written(histogram, "histogram")
    h = histogram.withColumn("block", F.floor(F.col("n_tokens") / F.lit(block)).cast("long")).withColumn("tokens", F.col("n_tokens") * F.col("n_docs"))
    blocks = h.groupBy("block").agg(F.sum("n_docs").alias("d"), F.sum("tokens").alias("t"))
    groups = blocks.withColumn("group", F.floor(F.col("block") / F.lit(block)).cast("long"))
    # blocks of blocks keep this step small too: its window never spans more than `block` rows
    later = Window.partitionBy("group").orderBy(F.col("block").desc()).rowsBetween(Window.unboundedPreceding, -1)
    tops = groups.groupBy("group").agg(F.sum("d").alias("gd"), F.sum("t").alias("gt"))
    # a row for each block * block lengths: a few at any size
    higher = Window.orderBy(F.col("group").desc()).rowsBetween(Window.unboundedPreceding, -1)
    zero = lambda c: F.coalesce(c, F.lit(0))
    above = tops.coalesce(1).select("group", zero(F.sum("gd").over(higher)).alias("ad"), zero(F.sum("gt").over(higher)).alias("at"))
    ahead = groups.select("group", "block", zero(F.sum("d").over(later)).alias("bd"), zero(F.sum("t").over(later)).alias("bt")).join(above, "group")
    ahead = ahead.select("block", (F.col("bd") + F.col("ad")).alias("d_after"), (F.col("bt") + F.col("at")).alias("t_after"))
    own = Window.partitionBy("block").orderBy(F.col("n_tokens").desc()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    total = histogram.agg(F.sum("n_docs").alias("all_docs"), F.sum(F.col("n_tokens") * F.col("n_docs")).alias("all_tokens"))
    return (
        h.join(ahead, "block")
        .withColumn("docs_at_least", F.sum("n_docs").over(own) + F.col("d_after"))
        .withColumn("tokens_at_least", F.sum("tokens").over(own) + F.col("t_after"))
        .crossJoin(F.broadcast(total))  # one row
        .select(
            "n_tokens",
            "n_docs",
            "docs_at_least",
            "tokens_at_least",
            (F.col("all_tokens") - F.col("tokens_at_least") + F.col("n_tokens") * F.col("docs_at_least")).alias("truncated_total"),
            (F.col("docs_at_least") - F.col("n_docs")).alias("docs_cut"),
            (F.col("all_docs") - F.col("docs_at_least")).alias("docs_below"),
        )
    )


def truncated_totals(histogram: DataFrame, limits: list[int]) -> DataFrame:
    """limit, truncated_total, docs_cut for each of a stated list of context limits, in one pass."""
    row = histogram.agg(
        *[F.sum(F.least(F.col("n_tokens"), F.lit(n)) * F.col("n_docs")).alias(f"t{n}") for n in limits],
        *[F.sum(F.when(F.col("n_tokens") > n, F.col("n_docs")).otherwise(0)).alias(f"c{n}") for n in limits],
    )
    pack: Column = F.explode(F.array(*[F.struct(F.lit(n).alias("limit"), F.col(f"t{n}").alias("truncated_total"), F.col(f"c{n}").alias("docs_cut")) for n in limits]))
    return row.select(pack.alias("r")).select("r.*")


def length_quantile(sums: DataFrame, share: float) -> DataFrame:
    """The smallest length with at least `share` of all documents at or below it."""
    return sums.filter(F.col("docs_below") + F.col("n_docs") >= F.lit(share) * (F.col("docs_below") + F.col("docs_at_least"))).agg(F.min("n_tokens").alias("n_tokens"))
