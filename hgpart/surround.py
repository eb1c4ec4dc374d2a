"""Relational, scalar, user-defined and file operators that users of the engine need around it.

Each is a query with its SQL equivalent beside it.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hgpart.functions import tables, udx
from hgpart.model import to_packed
from hgpart.plans.checkpoints import shared_folder
from hgpart.sources import files
from hgpart.sources.builders import BUILDERS

QUERIES: dict = {}
ORACLE: dict = {}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return register


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def _pins(spark: SparkSession, d: str) -> DataFrame:
    return BUILDERS["basket"](spark, d).pins


_PINS = (
    "WITH pins AS (SELECT p.e, p.n, p.n = h.head AS is_src, p.n <> h.head AS is_dst FROM (SELECT DISTINCT l_orderkey AS e, l_partkey AS n FROM lineitem) p "
    "JOIN (SELECT l_orderkey AS e, first(l_partkey ORDER BY l_linenumber, l_partkey) AS head FROM lineitem GROUP BY 1) h USING (e)) "
)


# scans, sources, sinks
@query("src_scan_pruned", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")
def src_scan_pruned(spark, d):
    return _t(spark, d, "lineitem").filter("l_quantity > 45 AND l_returnflag = 'R'").select("l_orderkey", "l_partkey")


def _roundtrip(kind: str):
    def run(spark, d):
        path = f"{shared_folder(spark)}/io-{kind}-{uuid.uuid4().hex}"
        if kind == "lines":
            files.write_edge_lines(_pins(spark, d), path)
            return files.read_edge_lines(spark, path)
        files.write_pins(_pins(spark, d), path, kind)
        return files.read_pins(spark, path, kind)

    return run


for _kind in (*files.FORMATS, "lines"):
    query(f"io_roundtrip_{_kind}", _PINS + "SELECT e, n, is_src, is_dst FROM pins")(_roundtrip(_kind))


@query("sink_partitioned", "SELECT (l_linenumber % 4)::INT AS level, count(*) AS n_rows FROM lineitem GROUP BY 1")
def sink_partitioned(spark, d):
    path = f"{shared_folder(spark)}/levels-{uuid.uuid4().hex}"
    files.write_levels(_t(spark, d, "lineitem").select(F.col("l_orderkey").alias("e"), F.col("l_partkey").alias("n"), F.expr("cast(l_linenumber % 4 as int)").alias("level")), path)
    return spark.read.parquet(path).groupBy("level").agg(F.count(F.lit(1)).alias("n_rows"))


@query("sql_api_view", _PINS + "SELECT n, count(*) AS degree FROM pins GROUP BY n HAVING count(*) > 20")
def sql_api_view(spark, d):
    name = f"pins_{uuid.uuid4().hex}"
    _pins(spark, d).createOrReplaceTempView(name)
    return spark.sql(f"SELECT n, count(*) AS degree FROM {name} GROUP BY n HAVING count(*) > 20")


@query("sink_bucketed", _PINS + "SELECT e, count(*) AS n_pins FROM pins GROUP BY e")
def sink_bucketed(spark, d):
    name = f"pins_{uuid.uuid4().hex}"
    files.write_bucketed(_pins(spark, d), name, f"{shared_folder(spark)}/{name}")
    return spark.table(name).groupBy("e").agg(F.count(F.lit(1)).alias("n_pins"))


@query("io_datasource", _PINS + "SELECT e AS id, list(n ORDER BY n) AS items FROM pins GROUP BY e")
def io_datasource(spark, d):
    path = f"{shared_folder(spark)}/packed-{uuid.uuid4().hex}"
    files.write_packed(to_packed(_pins(spark, d), "e", "n"), path)
    spark.dataSource.register(files.PackedSource)
    return spark.read.format("hgpart").load(path)


# relational
@query("rel_filter_pins", _PINS + "SELECT e, n FROM pins WHERE n BETWEEN 10 AND 60 AND e IN (SELECT o_orderkey FROM orders WHERE o_orderpriority LIKE '1-%') AND NOT is_src")
def rel_filter_pins(spark, d):
    urgent = _t(spark, d, "orders").filter(F.col("o_orderpriority").like("1-%")).select(F.col("o_orderkey").alias("e"))
    return _pins(spark, d).filter(F.col("n").between(10, 60) & ~F.col("is_src")).join(urgent, "e", "left_semi").select("e", "n")


@query("rel_case_roles", _PINS + "SELECT CASE WHEN is_src AND is_dst THEN 'both' WHEN is_src THEN 'source' ELSE 'destination' END AS role, count(*) AS n_pins FROM pins GROUP BY 1")
def rel_case_roles(spark, d):
    role = F.when(F.col("is_src") & F.col("is_dst"), "both").when(F.col("is_src"), "source").otherwise("destination")
    return _pins(spark, d).groupBy(role.alias("role")).agg(F.count(F.lit(1)).alias("n_pins"))


def _hinted(hint: str):
    def run(spark, d):
        assign = _t(spark, d, "part").select(F.col("p_partkey").alias("n"), F.expr("p_partkey % 16").alias("p")).hint(hint)
        return _pins(spark, d).join(assign, "n").groupBy("e", "p").agg(F.count(F.lit(1)).alias("cnt"))

    return run


for _hint in ("broadcast", "shuffle_hash", "merge"):
    query(f"join_{_hint}", _PINS + "SELECT e, n % 16 AS p, count(*) AS cnt FROM pins GROUP BY 1, 2")(_hinted(_hint))


@query("join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND (a.n_nationkey * b.n_nationkey) % 7 = 3")
def join_theta(spark, d):
    a, b = (_t(spark, d, "nation").select(F.col("n_nationkey").alias(k)) for k in "ab")
    return a.join(F.broadcast(b), (F.col("a") < F.col("b")) & (F.col("a") * F.col("b") % 7 == 3))  # 25 rows


@query("join_range", "SELECT e1.event_id AS a, e2.event_id AS b FROM events e1 JOIN events e2 ON e1.user_id = e2.user_id AND e2.ts > e1.ts AND e2.ts <= e1.ts + INTERVAL 1 HOUR")
def join_range(spark, d):
    """Events of a user within the next hour: both sides cut into hours, each event met in its own hour and the next."""
    e = _t(spark, d, "events").select("event_id", "user_id", "ts", F.floor(F.unix_timestamp("ts") / 3600).alias("h"))
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("t1"), F.explode(F.array(F.col("h"), F.col("h") + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("t2"), "h")
    return a.join(b, ["user_id", "h"]).filter("t2 > t1 AND t2 <= t1 + INTERVAL 1 HOUR").select("a", "b")


@query(
    "join_asof",
    "SELECT o_orderkey, max(event_id) FILTER (WHERE ts = last_ts) AS event_id FROM (SELECT o_orderkey, e.event_id, e.ts, max(e.ts) OVER (PARTITION BY o_orderkey) AS last_ts FROM orders JOIN events e ON e.user_id = o_custkey AND "
    "date_part('doy', e.ts) <= date_part('doy', o_orderdate)) GROUP BY o_orderkey",
)
def join_asof(spark, d):
    """The last event of each order's customer by day of year: both sides in one sorted window, no pairs."""
    events = _t(spark, d, "events").select(F.col("user_id").alias("k"), F.dayofyear("ts").alias("day"), F.lit(0).alias("side"), F.struct("ts", "event_id").alias("ev"), F.lit(None).cast("bigint").alias("o_orderkey"))
    orders = _t(spark, d, "orders").select(F.col("o_custkey").alias("k"), F.dayofyear("o_orderdate").alias("day"), F.lit(1).alias("side"), F.lit(None).cast(dict(events.dtypes)["ev"]).alias("ev"), "o_orderkey")
    upto = Window.partitionBy("k").orderBy("day", "side", F.col("ev.ts")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return events.unionByName(orders).withColumn("last", F.max("ev").over(upto)).filter("side = 1 AND last IS NOT NULL").select("o_orderkey", F.col("last.event_id").alias("event_id"))


@query("join_semi", _PINS + "SELECT DISTINCT e FROM pins SEMI JOIN (SELECT p_partkey AS n FROM part WHERE p_size > 45) USING (n)")
def join_semi(spark, d):
    return _pins(spark, d).join(_t(spark, d, "part").filter("p_size > 45").select(F.col("p_partkey").alias("n")), "n", "left_semi").select("e").distinct()


@query("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def join_anti(spark, d):
    urgent = _t(spark, d, "orders").filter("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("c_custkey"))
    return _t(spark, d, "customer").join(urgent, "c_custkey", "left_anti").select("c_custkey")


@query("join_left", "SELECT p_partkey, count(l_orderkey) AS n_lines FROM part LEFT JOIN lineitem ON p_partkey = l_partkey GROUP BY 1")
def join_left(spark, d):
    lines = _t(spark, d, "lineitem").groupBy(F.col("l_partkey").alias("p_partkey")).agg(F.count(F.lit(1)).alias("n_lines"))
    return _t(spark, d, "part").select("p_partkey").join(lines, "p_partkey", "left").na.fill(0)


@query("join_full", "SELECT coalesce(s.k, c.k) AS nation, s.x AS n_suppliers, c.x AS n_customers FROM (SELECT s_nationkey AS k, count(*) AS x FROM supplier GROUP BY 1) s FULL JOIN (SELECT c_nationkey AS k, count(*) AS x FROM customer GROUP BY 1) c ON s.k = c.k")
def join_full(spark, d):
    s = _t(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("n_suppliers"))
    c = _t(spark, d, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("n_customers"))
    return s.join(c, "nation", "full_outer").select("nation", "n_suppliers", "n_customers")


@query("join_cross", "SELECT n_nationkey, r_regionkey FROM nation, region")
def join_cross(spark, d):
    return _t(spark, d, "nation").select("n_nationkey").crossJoin(F.broadcast(_t(spark, d, "region").select("r_regionkey")))  # 5 rows


@query("join_lateral", "SELECT r_regionkey, x.n_nationkey FROM region, LATERAL (SELECT n_nationkey FROM nation WHERE n_regionkey = r_regionkey ORDER BY n_nationkey LIMIT 2) x")
def join_lateral(spark, d):
    nations = _t(spark, d, "nation")
    best = nations.filter(F.col("n_regionkey") == F.col("r_regionkey").outer()).orderBy("n_nationkey").limit(2).select("n_nationkey")
    return _t(spark, d, "region").lateralJoin(best).select("r_regionkey", "n_nationkey")


@query("agg_degree", _PINS + "SELECT n, count(*) AS degree, count(DISTINCT e % 10) AS residues, bool_or(is_src) AS ever_source FROM pins GROUP BY n")
def agg_degree(spark, d):
    return _pins(spark, d).groupBy("n").agg(F.count(F.lit(1)).alias("degree"), F.countDistinct(F.expr("e % 10")).alias("residues"), F.bool_or("is_src").alias("ever_source"))


@query("agg_distinct", _PINS + "SELECT e, count(DISTINCT n % 7) AS n_residues, sum(DISTINCT n % 7)::BIGINT AS sum_residues, count(DISTINCT (n % 3, is_src)) AS n_pairs FROM pins GROUP BY e")
def agg_distinct(spark, d):
    return _pins(spark, d).groupBy("e").agg(F.countDistinct(F.expr("n % 7")).alias("n_residues"), F.sum_distinct(F.expr("n % 7")).alias("sum_residues"), F.countDistinct(F.struct(F.expr("n % 3"), "is_src")).alias("n_pairs"))


@query("agg_bool", _PINS + "SELECT n, bool_or(is_src) AS ever_source, bool_and(is_dst) AS always_target, count(*) FILTER (WHERE is_src) AS n_source FROM pins GROUP BY n")
def agg_bool(spark, d):
    return _pins(spark, d).groupBy("n").agg(F.bool_or("is_src").alias("ever_source"), F.bool_and("is_dst").alias("always_target"), F.count_if("is_src").alias("n_source"))


@query("agg_maxby", "SELECT o_custkey, max(o_totalprice) AS top, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS at FROM orders GROUP BY 1")
def agg_maxby(spark, d):
    return _t(spark, d, "orders").groupBy("o_custkey").agg(F.max("o_totalprice").alias("top"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("at"))


@query("agg_collect", "SELECT l_suppkey, list(DISTINCT l_linenumber ORDER BY l_linenumber) AS numbers FROM lineitem GROUP BY 1")
def agg_collect(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_suppkey").agg(F.array_sort(F.collect_set("l_linenumber")).alias("numbers"))


@query("approx_union_size")
def approx_union_size(spark, d):
    """In-set unions of parts by brand, exact and by a sketch that merges."""
    pins = _pins(spark, d).filter("is_dst").join(_t(spark, d, "part").select(F.col("p_partkey").alias("n"), "p_brand"), "n")
    return pins.groupBy("p_brand").agg(F.countDistinct("e").alias("exact"), F.hll_sketch_estimate(F.hll_sketch_agg("e")).alias("estimate"), F.approx_count_distinct("e").alias("approx"))


def _by_place(spark, d):
    return _t(spark, d, "customer").join(F.broadcast(_t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("n_regionkey", "c_mktsegment")  # 25 rows


_PLACE = "FROM customer JOIN nation ON c_nationkey = n_nationkey"


@query("agg_cube", f"SELECT n_regionkey, c_mktsegment, count(*) AS n_rows {_PLACE} GROUP BY CUBE (n_regionkey, c_mktsegment)")
def agg_cube(spark, d):
    return _by_place(spark, d).cube("n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n_rows"))


@query("agg_rollup", f"SELECT n_regionkey, c_mktsegment, count(*) AS n_rows {_PLACE} GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
def agg_rollup(spark, d):
    return _by_place(spark, d).rollup("n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n_rows"))


@query("agg_grouping_sets", f"SELECT n_regionkey, c_mktsegment, count(*) AS n_rows {_PLACE} GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment))")
def agg_grouping_sets(spark, d):
    return _by_place(spark, d).groupingSets([[F.col("n_regionkey")], [F.col("c_mktsegment")]], "n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n_rows"))


@query("agg_pivot", "SELECT l_linenumber, count(*) FILTER (WHERE l_returnflag = 'A') AS a, count(*) FILTER (WHERE l_returnflag = 'N') AS n, count(*) FILTER (WHERE l_returnflag = 'R') AS r FROM lineitem GROUP BY 1")
def agg_pivot(spark, d):
    wide = _t(spark, d, "lineitem").groupBy("l_linenumber").pivot("l_returnflag", ["A", "N", "R"]).count().na.fill(0)
    return wide.select("l_linenumber", F.col("A").alias("a"), F.col("N").alias("n"), F.col("R").alias("r"))


@query("win_rank", "SELECT o_orderkey, (rank() OVER w)::INT AS r, (dense_rank() OVER w)::INT AS dr, (ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_orderkey))::INT AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def win_rank(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return _t(spark, d, "orders").select("o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(Window.partitionBy("o_custkey").orderBy("o_orderkey")).alias("q"))


@query("win_lag", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return _t(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"))


@query("win_running", "SELECT l_orderkey, l_partkey, l_linenumber, (sum(q) OVER w)::BIGINT AS running, (max(q) OVER w)::BIGINT AS top, avg(q) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, q ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS near FROM (SELECT *, l_quantity::BIGINT AS q FROM lineitem) WINDOW w AS (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, q ROWS UNBOUNDED PRECEDING)")
def win_running(spark, d):
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "q")
    up = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = _t(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber", F.col("l_quantity").cast("bigint").alias("q"))
    return rows.select("l_orderkey", "l_partkey", "l_linenumber", F.sum("q").over(up).alias("running"), F.max("q").over(up).alias("top"), F.avg("q").over(w.rowsBetween(-1, 1)).alias("near"))


@query("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS last_day FROM events")
def win_range(spark, d):
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)
    return _t(spark, d, "events").select("event_id", "user_id", F.unix_timestamp("ts").alias("s")).select("event_id", F.count(F.lit(1)).over(w).alias("last_day"))


@query("sort_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def sort_topk(spark, d):
    return _t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20)


@query("topk_per_group", "SELECT l_suppkey, l_partkey, q FROM (SELECT l_suppkey, l_partkey, q, row_number() OVER (PARTITION BY l_suppkey ORDER BY q DESC, l_partkey) AS r FROM (SELECT l_suppkey, l_partkey, sum(l_quantity)::BIGINT AS q FROM lineitem GROUP BY 1, 2)) WHERE r <= 3")
def topk_per_group(spark, d):
    sums = _t(spark, d, "lineitem").groupBy("l_suppkey", "l_partkey").agg(F.sum(F.col("l_quantity").cast("bigint")).alias("q"))
    rank = F.row_number().over(Window.partitionBy("l_suppkey").orderBy(F.col("q").desc(), "l_partkey"))
    return sums.withColumn("r", rank).filter("r <= 3").select("l_suppkey", "l_partkey", "q")


def _two_sets(spark, d):
    p = _pins(spark, d).select("e", "n")
    return p.filter("n % 2 = 0"), p.filter("n % 3 = 0")


@query("set_union", _PINS + "SELECT e, n FROM pins WHERE n % 2 = 0 UNION ALL SELECT e, n FROM pins WHERE n % 3 = 0")
def set_union(spark, d):
    a, b = _two_sets(spark, d)
    return a.unionByName(b)


@query("set_intersect", _PINS + "SELECT e, n FROM pins WHERE n % 6 = 0")
def set_intersect(spark, d):
    a, b = _two_sets(spark, d)
    return a.intersectAll(b)


@query("set_except", _PINS + "SELECT e, n FROM pins WHERE n % 2 = 0 AND n % 3 <> 0")
def set_except(spark, d):
    a, b = _two_sets(spark, d)
    return a.exceptAll(b)


def _sql(text: str, *tables: str):
    def run(spark, d):
        for t in tables:
            _t(spark, d, t).createOrReplaceTempView(f"hgv_{t}")
        return spark.sql(text.replace("{", "hgv_").replace("}", ""))

    return run


def sql_query(name: str, text: str, *tables: str) -> None:
    """The same text for both engines, tables in braces."""
    query(name, text.replace("{", "").replace("}", ""))(_sql(text, *tables))


sql_query("sql_cte", "WITH big AS (SELECT o_custkey, count(*) AS c FROM {orders} GROUP BY o_custkey) SELECT c, count(*) AS n_customers FROM big GROUP BY c", "orders")
sql_query("sql_correlated", "SELECT c_custkey, (SELECT count(*) FROM {orders} WHERE o_custkey = c_custkey) AS n_orders FROM {customer}", "orders", "customer")
sql_query("sql_exists", "SELECT p_partkey FROM {part} WHERE EXISTS (SELECT 1 FROM {lineitem} WHERE l_partkey = p_partkey AND l_quantity > 49)", "part", "lineitem")
sql_query("sql_recursive", "WITH RECURSIVE walk(k, steps) AS (SELECT n_nationkey, 0 FROM {nation} UNION ALL SELECT k - 5, steps + 1 FROM walk WHERE k >= 5) SELECT k, max(steps) AS steps FROM walk GROUP BY k", "nation")


@query("sample_hash", "SELECT event_id FROM events WHERE event_id * 2654435761 % 1000 < 100")
def sample_hash(spark, d):
    return _t(spark, d, "events").filter(F.expr("event_id * 2654435761L % 1000 < 100")).select("event_id")


# scalar functions
@query("fn_string", "SELECT doc_id, length(text) AS n, upper(substr(lang, 1, 1)) || source AS tag, len(string_split(text, ' ')) AS blanks, regexp_replace(source, '[0-9]+', '#') AS kind FROM documents")
def fn_string(spark, d):
    return _t(spark, d, "documents").select("doc_id", F.length("text").cast("bigint").alias("n"), F.concat(F.upper(F.substring("lang", 1, 1)), "source").alias("tag"), F.size(F.split("text", " ")).cast("bigint").alias("blanks"), F.regexp_replace("source", "[0-9]+", "#").alias("kind"))


@query("fn_date", "SELECT event_id, date_trunc('hour', ts)::TIMESTAMP AS hour, year(ts)::INT AS y, date_diff('day', DATE '2024-01-01', ts::DATE)::INT AS day, floor(epoch(ts))::BIGINT AS s FROM events")
def fn_date(spark, d):
    return _t(spark, d, "events").select("event_id", F.date_trunc("hour", "ts").alias("hour"), F.year("ts").alias("y"), F.date_diff(F.to_date("ts"), F.to_date(F.lit("2024-01-01"))).alias("day"), F.unix_timestamp("ts").alias("s"))


@query("fn_math", "SELECT p_partkey, ceil(p_size / 16.0)::BIGINT AS parts, bit_count(p_partkey)::INT AS bits, p_partkey & 7 AS low, round(log2(p_size + 1), 6) AS lg FROM part")
def fn_math(spark, d):
    return _t(spark, d, "part").select("p_partkey", F.ceil(F.col("p_size") / 16.0).cast("bigint").alias("parts"), F.bit_count("p_partkey").alias("bits"), F.col("p_partkey").bitwiseAND(F.lit(7).cast("bigint")).alias("low"), F.round(F.log2(F.col("p_size") + 1), 6).alias("lg"))


@query("fn_array", "SELECT vec_id, round(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)), 4) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def fn_array(spark, d):
    e = F.col("embedding").cast("array<double>")
    return _t(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform(e, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 4).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"))


@query("fn_map", "SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'O') AS open FROM orders GROUP BY 1")
def fn_map(spark, d):
    counts = _t(spark, d, "orders").groupBy("o_custkey", "o_orderstatus").agg(F.count(F.lit(1)).alias("c"))
    maps = counts.groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "c"))).alias("m"))
    return maps.select("o_custkey", F.coalesce(F.element_at("m", "O"), F.lit(0)).cast("bigint").alias("open"))


@query("fn_json", "SELECT event_id, json_extract_string(props, '$.k')::INT AS k FROM events")
def fn_json(spark, d):
    return _t(spark, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k"))


# user-defined
@query("udf_cosine", "SELECT vec_id, round(list_cosine_similarity(embedding::DOUBLE[], (SELECT embedding::DOUBLE[] FROM embeddings WHERE vec_id = 0)), 4) AS cos FROM embeddings")
def udf_cosine(spark, d):
    v = _t(spark, d, "embeddings")
    first = v.filter("vec_id = 0").select(F.col("embedding").alias("other"))
    return v.crossJoin(F.broadcast(first)).select("vec_id", F.round(udx.cosine("embedding", "other"), 4).alias("cos"))  # one row


@query("udaf_inbound", _PINS + "SELECT n % 16 AS p, count(DISTINCT e) AS inbound FROM pins WHERE is_dst GROUP BY 1")
def udaf_inbound(spark, d):
    return _pins(spark, d).filter("is_dst").groupBy(F.expr("n % 16").alias("p")).agg(udx.distinct_inbound("e").alias("inbound"))


@query("udtf_pairs", _PINS + "SELECT a.e, a.n, b.n AS m FROM pins a JOIN pins b ON a.e = b.e AND a.n < b.n")
def udtf_pairs(spark, d):
    """Pairs of each hyperedge by a table function over packed pins; for hyperedges of bounded size."""
    packed = _pins(spark, d).groupBy("e").agg(F.array_sort(F.collect_list("n")).alias("items"))
    spark.udtf.register("hg_co_pins", tables.CoPins)
    name = f"packed_{uuid.uuid4().hex}"
    packed.createOrReplaceTempView(name)
    return spark.sql(f"SELECT e, t.n, t.m FROM {name}, LATERAL hg_co_pins(items) t")
