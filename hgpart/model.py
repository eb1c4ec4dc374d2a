"""Directed weighted hypergraphs as DataFrames, and the limits of a partition.

pins(e, n, is_src, is_dst) is unique on (e, n); edges(e, w, mult) on e; nodes(n, size) on n. Weights are
whole numbers, so sums are exact in any order and ties are decided alike on every run. mult
counts hyperedges that were merged into one.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

NO_LIMIT = 1 << 62
BOUND_COLUMNS = {"in": "is_dst", "out": "is_src", "incident": None}


@dataclass(frozen=True)
class Limits:
    max_nodes: int = NO_LIMIT
    max_inbound: int = NO_LIMIT
    bound_on: str = "in"

    def __post_init__(self):
        if self.max_nodes < 1 or self.max_inbound < 0 or self.bound_on not in BOUND_COLUMNS:
            raise ValueError(f"bad limits: {self}")

    def bound(self, prefix: str = "") -> Column:
        """Whether a pin counts towards the limit on distinct hyperedges."""
        name = BOUND_COLUMNS[self.bound_on]
        return F.col(prefix + name) if name else F.lit(True)


@dataclass(frozen=True)
class Hypergraph:
    pins: DataFrame
    edges: DataFrame
    nodes: DataFrame

    @staticmethod
    def from_pins(rows: DataFrame, weights: DataFrame | None = None, nodes: DataFrame | None = None) -> Hypergraph:
        """From coordinate rows (e, n[, is_src, is_dst]); repeated pins merge, weights default to 1,
        nodes to those with a pin. A node that is neither source nor destination is a destination."""
        has = lambda c: F.col(c) if c in rows.columns else F.lit(None).cast("boolean")
        pins = rows.select(
            F.col("e").cast("bigint").alias("e"),
            F.col("n").cast("bigint").alias("n"),
            F.coalesce(has("is_src"), F.lit(False)).alias("is_src"),
            F.coalesce(has("is_dst"), ~F.coalesce(has("is_src"), F.lit(False))).alias("is_dst"),
        )
        pins = pins.groupBy("e", "n").agg(F.bool_or("is_src").alias("is_src"), F.bool_or("is_dst").alias("is_dst"))
        if weights is None:
            edges = pins.select("e").distinct().select("e", F.lit(1).cast("bigint").alias("w"), F.lit(1).alias("mult"))
        else:
            edges = weights.select(F.col("e").cast("bigint").alias("e"), F.col("w").cast("bigint").alias("w"), F.lit(1).alias("mult"))
        if nodes is None:
            nodes = pins.select("n").distinct()
        return Hypergraph(pins, edges, nodes.select(F.col("n").cast("bigint").alias("n"), F.lit(1).cast("bigint").alias("size")))

    @property
    def weighted_pins(self) -> DataFrame:
        return self.pins.join(self.edges, "e")


def global_rank(df: DataFrame, *order: Column, name: str = "idx") -> DataFrame:
    """df with `name` = 1, 2, ... in a total order, without a one-task window: range partitions are
    ranked alone and shifted by the sizes of those before. order must leave no ties."""
    from hgpart.plans.checkpoints import materialize

    ranged = df.repartitionByRange(*order).withColumn("r__part", F.spark_partition_id())
    ranged = materialize(ranged, "ranged")  # the partition number must not change on retries
    sizes = ranged.groupBy("r__part").agg(F.count(F.lit(1)).alias("r__n"))
    # one row per partition of the range exchange
    before = Window.orderBy("r__part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.coalesce(1).select("r__part", F.coalesce(F.sum("r__n").over(before), F.lit(0)).alias("r__before"))
    own = Window.partitionBy("r__part").orderBy(*order)
    return (
        ranged.withColumn("r__own", F.row_number().over(own))
        .join(F.broadcast(offsets), "r__part")
        .withColumn(name, (F.col("r__own") + F.col("r__before")).cast("bigint"))
        .drop("r__part", "r__own", "r__before")
    )


def global_scan(df: DataFrame, index: str, value: str, name: str, block: int = 1 << 16) -> DataFrame:
    """df with the running sum of value over index (whole numbers from 1, unique), in two levels."""
    blocked = df.withColumn("s__block", F.floor(F.col(index) / F.lit(block)).cast("bigint"))
    sums = blocked.groupBy("s__block").agg(F.sum(value).alias("s__sum"))
    before = Window.orderBy("s__block").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.coalesce(1).select("s__block", F.coalesce(F.sum("s__sum").over(before), F.lit(0)).alias("s__before"))
    own = Window.partitionBy("s__block").orderBy(index).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return (
        blocked.withColumn("s__own", F.sum(value).over(own))
        .join(offsets, "s__block")
        .withColumn(name, (F.col("s__own") + F.col("s__before")).cast("bigint"))
        .drop("s__block", "s__own", "s__before")
    )


def segmented_scan(df: DataFrame, keys: list[str], order: str, value: str, name: str, block: int | None = None) -> DataFrame:
    """df with the running sum of value by order (unique whole numbers for each key). With block, the rows of a key are dealt to
    blocks of that many order values and shifted by the sums of the blocks before, so that no task has a crowded key alone."""
    if block:
        blocked = df.withColumn("s__block", F.floor(F.col(order) / F.lit(block)).cast("bigint"))
        sums = blocked.groupBy(*keys, "s__block").agg(F.sum(value).alias("s__sum"))
        before = Window.partitionBy(*keys).orderBy("s__block").rowsBetween(Window.unboundedPreceding, -1)
        offsets = sums.select(*keys, "s__block", F.coalesce(F.sum("s__sum").over(before), F.lit(0)).alias("s__before"))
        own = segmented_scan(blocked, [*keys, "s__block"], order, value, "s__own").join(offsets, [*keys, "s__block"])
        return own.withColumn(name, F.col("s__own") + F.col("s__before")).select(*df.columns, name)
    w = Window.partitionBy(*keys).orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return df.withColumn(name, F.sum(value).over(w))


_TEN19 = "10000000000000000000"


def argmax_by(df: DataFrame, key: str, value: str, ident: str, bounds: tuple[int, int] | None = None) -> DataFrame:
    """(key, value, ident) with the largest (value, ident) of each key; both at least 0.

    Packed into one number, the maximum stays a hash aggregate; a struct would sort. The number is a BIGINT if bounds, the
    largest value and ident there may be, say that it fits, else a DECIMAL(38, 0)."""
    if bounds and bounds[0] < 1 << (63 - (bits := max(1, bounds[1].bit_length()))):
        best = df.groupBy(key).agg(F.max(F.expr(f"shiftleft({value}, {bits}) | {ident}")).alias("a__p"))
        return best.select(key, F.expr(f"shiftright(a__p, {bits})").alias(value), F.expr(f"a__p & {(1 << bits) - 1}L").alias(ident))
    packed = F.expr(f"cast({value} as decimal(19, 0)) * {_TEN19} + cast({ident} as decimal(19, 0))").cast("decimal(38, 0)")
    best = df.groupBy(key).agg(F.max(packed).alias("a__p"))
    return best.select(key, F.expr(f"cast(a__p div {_TEN19} as bigint)").alias(value), F.expr(f"cast(a__p % {_TEN19} as bigint)").alias(ident))


def assign_ids(df: DataFrame, key: str, name: str = "id") -> DataFrame:
    """key and zero-based dense ids in the order of the distinct keys; null keys have none."""
    keys = df.select(key).filter(F.col(key).isNotNull()).distinct()
    return global_rank(keys, F.col(key), name=name).withColumn(name, F.col(name) - 1)


def incidence(hg: Hypergraph, kind: str = "all") -> DataFrame:
    """(n, items): sorted hyperedges that n is a destination of ("in"), a source of ("out"), or a pin of ("all")."""
    rows = {"in": hg.pins.filter("is_dst"), "out": hg.pins.filter("is_src"), "all": hg.pins}[kind]
    return rows.groupBy("n").agg(F.array_sort(F.collect_list("e")).alias("items"))


def incidence_sizes(hg: Hypergraph) -> DataFrame:
    return hg.nodes.select("n").join(
        hg.pins.groupBy("n").agg(F.count_if("is_dst").alias("n_in"), F.count_if("is_src").alias("n_out"), F.count(F.lit(1)).alias("n_all")), "n", "left"
    ).na.fill(0)


def cells(pins: DataFrame, chunk: int) -> tuple[DataFrame, DataFrame]:
    """pins twice, as left and right sides to be joined on (e, i, j): the pins of a hyperedge are dealt to chunks of about `chunk`, and
    cell (i, j), i <= j, has chunk i on the left and chunk j on the right. So a hyperedge of any size is spread over tasks
    that each get chunk * chunk pairs. Every pair of pins meets once, but within a chunk (i = j) both ways."""
    sizes = pins.groupBy("e").agg(F.count(F.lit(1)).alias("s")).filter(F.col("s") > chunk)
    dealt = pins.join(sizes, "e", "left").withColumn("s", F.coalesce(F.ceil(F.col("s") / chunk), F.lit(1))).withColumn("c", F.pmod(F.xxhash64("n"), F.col("s")))
    left = dealt.withColumnRenamed("c", "i").withColumn("j", F.explode(F.sequence("i", F.col("s") - 1))).drop("s")
    right = dealt.withColumnRenamed("c", "j").withColumn("i", F.explode(F.sequence(F.lit(0).cast("bigint"), "j"))).drop("s")
    return left, right


def neighbors(hg: Hypergraph, chunk: int | None = None) -> DataFrame:
    """(n, m) for all nodes that share a hyperedge, both ways, n <> m; hyperedges of over `chunk` pins are joined by cells."""
    if chunk:
        a, b = cells(hg.pins.select("e", "n"), chunk)
        once = a.join(b.withColumnRenamed("n", "m"), ["e", "i", "j"]).filter("n <> m").select(F.least("n", "m").alias("n"), F.greatest("n", "m").alias("m")).distinct()
        return once.select(F.explode(F.array(F.struct("n", "m"), F.struct(F.col("m").alias("n"), F.col("n").alias("m")))).alias("x")).select("x.n", "x.m")
    a, b = hg.pins.select("e", "n"), hg.pins.select("e", F.col("n").alias("m"))
    return a.join(b, "e").filter("n <> m").select("n", "m").distinct()


def to_packed(sets: DataFrame, key: str, item: str) -> DataFrame:
    return sets.groupBy(F.col(key).alias("id")).agg(F.array_sort(F.collect_set(item)).alias("items"))


def from_packed(packed: DataFrame, key: str, item: str) -> DataFrame:
    return packed.select(F.col("id").alias(key), F.explode("items").alias(item))


def to_csr(packed: DataFrame) -> DataFrame:
    """(id, start, length): where each id's items lie in the one data array of all."""
    sized = packed.select("id", F.size("items").cast("bigint").alias("length"))
    ranked = global_rank(sized, F.col("id"), name="k")
    return global_scan(ranked, "k", "length", "stop").select("id", (F.col("stop") - F.col("length")).alias("start"), "length")


def validate(hg: Hypergraph, limits: Limits) -> DataFrame:
    """(problem, n_rows): repeated pins, negative weights, pins without edge or node, nodes that no partition can hold."""
    deg = hg.weighted_pins.filter(limits.bound()).groupBy("n").agg(F.sum("mult").alias("d"))
    checks = [
        ("duplicate_pins", hg.pins.groupBy("e", "n").count().filter("count > 1")),
        ("negative_weights", hg.edges.filter("w < 0")),
        ("pins_without_edge", hg.pins.join(hg.edges, "e", "left_anti")),
        ("pins_without_node", hg.pins.join(hg.nodes, "n", "left_anti")),
        ("oversized_nodes", hg.nodes.filter(F.col("size") > limits.max_nodes)),
        ("overbound_nodes", deg.filter(F.col("d") > limits.max_inbound)),
    ]
    out = None
    for name, rows in checks:
        one = rows.agg(F.count(F.lit(1)).alias("n_rows")).select(F.lit(name).alias("problem"), "n_rows")
        out = one if out is None else out.unionByName(one)
    return out


def stats(hg: Hypergraph) -> DataFrame:
    """One row: nodes, hyperedges, pins, the largest hyperedge, unordered co-pin pairs, largest in-degree."""
    sizes = hg.pins.groupBy("e").agg(F.count(F.lit(1)).alias("s")).agg(
        F.count(F.lit(1)).alias("n_edges"),
        F.sum("s").alias("n_pins"),
        F.max("s").alias("max_edge"),
        F.sum(F.expr("s * (s - 1) div 2")).alias("n_pairs"),
        F.count_if(F.col("s") == 1).alias("n_single"),
    )
    degrees = hg.pins.filter("is_dst").groupBy("n").agg(F.count(F.lit(1)).alias("d")).agg(F.coalesce(F.max("d"), F.lit(0)).alias("max_in"))
    nodes = hg.nodes.agg(F.count(F.lit(1)).alias("n_nodes"))
    return nodes.crossJoin(F.broadcast(sizes)).crossJoin(F.broadcast(degrees))  # one row each


def merge_parallel(hg: Hypergraph) -> Hypergraph:
    """Hyperedges with the same sources and destinations become one: weights and mult add up.

    Exact: connections and gains use summed weights, the inbound limit uses mult."""
    key = F.array_sort(F.collect_list(F.struct("n", "is_src", "is_dst")))
    same = hg.pins.groupBy("e").agg(F.sha2(key.cast("string"), 256).alias("k"), F.count(F.lit(1)).alias("s"))
    first = same.join(hg.edges, "e").groupBy("k", "s").agg(F.min("e").alias("first"), F.sum("w").alias("w"), F.sum("mult").cast("int").alias("mult"))
    edges = first.select(F.col("first").alias("e"), "w", "mult")
    return Hypergraph(hg.pins.join(edges.select("e"), "e", "left_semi"), edges, hg.nodes)
