"""DuckDB equivalents, put together from common table expressions."""

from __future__ import annotations

import re

from hgpart.sources.builders import LAYER, REGIMES

_HEAD = "SELECT p.e, p.n, p.n = h.head AS is_src, p.n <> h.head AS is_dst FROM ({pins}) p JOIN ({head}) h USING (e)"
_DST = "SELECT DISTINCT {e} AS e, {n} AS n, false AS is_src, true AS is_dst FROM lineitem"
_TOKENS = "SELECT DISTINCT {n} AS n, unnest(string_split_regex(lower(text), '[^\\p{{L}}0-9]+')) AS token FROM {t}"


def _token_ctes(table: str, n: str) -> dict[str, str]:
    return {
        "tok": f"SELECT DISTINCT n, token FROM ({_TOKENS.format(n=n, t=table)}) WHERE token <> ''",
        "tdf": "SELECT token, min(n) AS head, row_number() OVER (ORDER BY token) - 1 AS e FROM tok GROUP BY token HAVING count(*) BETWEEN 2 AND 32",
        "pins": "SELECT e, n, n = head AS is_src, n <> head AS is_dst FROM tok JOIN tdf USING (token)",
        "edges": "SELECT e, 1::BIGINT AS w, 1 AS mult FROM tdf",
        "nodes": f"SELECT DISTINCT {n} AS n, 1::BIGINT AS size FROM {table}",
    }


_PLAIN = {"edges": "SELECT DISTINCT e, 1::BIGINT AS w, 1 AS mult FROM pins"}


def workload_ctes(name: str) -> dict[str, str]:
    if name == "basket":
        return {
            "pins": _HEAD.format(pins="SELECT DISTINCT l_orderkey AS e, l_partkey AS n FROM lineitem", head="SELECT l_orderkey AS e, first(l_partkey ORDER BY l_linenumber, l_partkey) AS head FROM lineitem GROUP BY 1"),
            "edges": "SELECT l_orderkey AS e, sum(l_quantity)::BIGINT AS w, 1 AS mult FROM lineitem GROUP BY 1",
            "nodes": "SELECT p_partkey AS n, 1::BIGINT AS size FROM part",
        }
    if name == "copurchase":
        return {
            "bought": "SELECT l_partkey AS e, o_custkey AS n, o_orderdate AS d FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
            "pins": _HEAD.format(pins="SELECT DISTINCT e, n FROM bought", head="SELECT e, first(n ORDER BY d, n) AS head FROM bought GROUP BY e"),
            "edges": "SELECT p_partkey AS e, p_size::BIGINT AS w, 1 AS mult FROM part WHERE p_partkey IN (SELECT e FROM bought)",
            "nodes": "SELECT c_custkey AS n, 1::BIGINT AS size FROM customer",
        }
    if name == "sourcing":
        return {"pins": _DST.format(e="l_suppkey", n="l_partkey"), **_PLAIN, "nodes": "SELECT p_partkey AS n, 1::BIGINT AS size FROM part"}
    if name == "suppliers":
        return {
            "pins": _DST.format(e="l_partkey", n="l_suppkey"),
            "edges": "SELECT p_partkey AS e, p_size::BIGINT AS w, 1 AS mult FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem)",
            "nodes": "SELECT s_suppkey AS n, 1::BIGINT AS size FROM supplier",
        }
    if name == "terms":
        return _token_ctes("documents", "doc_id")
    if name == "dialog":
        return _token_ctes("conversations", "conv_id")
    if name == "links":
        return {
            "href": "SELECT DISTINCT page_id AS n, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages",
            "hid": "SELECT href, min(n) AS head, row_number() OVER (ORDER BY href) - 1 AS e FROM href GROUP BY href",
            "pins": "SELECT e, n, n = head AS is_src, n <> head AS is_dst FROM href JOIN hid USING (href)",
            **_PLAIN,
            "nodes": "SELECT page_id AS n, 1::BIGINT AS size FROM pages",
        }
    if name == "cohort":
        return {
            "hid": "SELECT date_trunc('hour', ts) AS hour, event_type, first(user_id ORDER BY ts, event_id, user_id) AS head, count(*) AS w, "
            "row_number() OVER (ORDER BY strftime(date_trunc('hour', ts), '%Y-%m-%d %H') || '|' || event_type) - 1 AS e FROM events GROUP BY 1, 2",
            "pins": "SELECT DISTINCT e, user_id AS n, user_id = head AS is_src, user_id <> head AS is_dst FROM events JOIN hid ON date_trunc('hour', ts) = hour AND events.event_type = hid.event_type",
            "edges": "SELECT e, w::BIGINT AS w, 1 AS mult FROM hid",
            "nodes": "SELECT DISTINCT user_id AS n, 1::BIGINT AS size FROM events",
        }
    if name == "trade":
        return {
            "sides": "SELECT l_partkey AS e, s_nationkey::BIGINT AS n, true AS s, false AS d FROM lineitem JOIN supplier ON l_suppkey = s_suppkey UNION ALL "
            "SELECT l_partkey, c_nationkey::BIGINT, false, true FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey",
            "pins": "SELECT e, n, bool_or(s) AS is_src, bool_or(d) AS is_dst FROM sides GROUP BY e, n",
            "edges": "SELECT l_partkey AS e, count(*)::BIGINT AS w, 1 AS mult FROM lineitem GROUP BY 1",
            "nodes": "SELECT n_nationkey::BIGINT AS n, 1::BIGINT AS size FROM nation",
        }
    if name == "knn":
        return {
            "near": "SELECT e, n FROM (SELECT a.vec_id AS e, b.vec_id AS n, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) DESC, b.vec_id) AS r "
            "FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 8",
            "pins": "SELECT e, n, false AS is_src, true AS is_dst FROM near UNION ALL SELECT vec_id, vec_id, true, false FROM embeddings",
            **_PLAIN,
            "nodes": "SELECT vec_id AS n, 1::BIGINT AS size FROM embeddings",
        }
    if name == "layered":
        hops = [("c_nationkey", "c_custkey", "customer"), ("o_custkey", "o_orderkey", "orders"), ("l_orderkey", "l_partkey", "lineitem")]
        parts = []
        for k, (a, b, t) in enumerate(hops):
            parts.append(f"SELECT {a} + {k * LAYER} AS e, {a} + {k * LAYER} AS n, true AS s, false AS d FROM {t}")
            parts.append(f"SELECT {a} + {k * LAYER}, {b} + {(k + 1) * LAYER}, false, true FROM {t}")
        keys = [("nation", "n_nationkey"), ("customer", "c_custkey"), ("orders", "o_orderkey"), ("part", "p_partkey")]
        return {
            "sides": " UNION ALL ".join(parts),
            "pins": "SELECT e::BIGINT AS e, n::BIGINT AS n, bool_or(s) AS is_src, bool_or(d) AS is_dst FROM sides GROUP BY e, n",
            **_PLAIN,
            "nodes": " UNION ALL ".join(f"SELECT ({c} + {k * LAYER})::BIGINT AS n, 1::BIGINT AS size FROM {t}" for k, (t, c) in enumerate(keys)),
        }
    raise KeyError(name)


def limit_cte(name: str) -> str:
    nodes, share = REGIMES[name]
    return f"SELECT {nodes}::BIGINT AS om, ({share} * coalesce(max(d), 0) // 100)::BIGINT AS de FROM (SELECT count(*) AS d FROM pins WHERE is_dst GROUP BY n)"


def level_ctes(k: int, bound: str = "is_dst") -> dict[str, str]:
    """Candidates, matching and contraction of level k (pins0 and nodes0 are the given ones)."""
    p, v = f"pins{k}", f"nodes{k}"
    on = (lambda a: "true") if bound == "incident" else (lambda a: f"{a}.{bound}")
    return {
        f"conn{k}": f"SELECT a.n, b.n AS m, sum(w)::BIGINT AS hist, sum(CASE WHEN {on('a')} AND {on('b')} THEN mult ELSE 0 END)::BIGINT AS shared_in FROM {p} a JOIN {p} b ON a.e = b.e AND a.n < b.n JOIN edges x ON x.e = a.e GROUP BY a.n, b.n",
        f"load{k}": f"SELECT n, size, coalesce(deg, 0)::BIGINT AS deg FROM {v} LEFT JOIN (SELECT p.n, sum(mult) AS deg FROM {p} p JOIN edges USING (e) WHERE {on('p')} GROUP BY p.n) USING (n)",
        f"valid{k}": f"SELECT c.n, c.m, hist, shared_in FROM conn{k} c JOIN load{k} a ON a.n = c.n JOIN load{k} b ON b.n = c.m, lim WHERE a.size + b.size <= om AND a.deg + b.deg - shared_in <= de",
        f"both{k}": f"SELECT n, m AS cand, hist AS score FROM valid{k} UNION ALL SELECT m, n, hist FROM valid{k}",
        f"prop{k}": f"SELECT n, cand, score FROM (SELECT *, row_number() OVER (PARTITION BY n ORDER BY score DESC, cand DESC) AS r FROM both{k}) WHERE r = 1",
        f"root{k}": f"SELECT a.n, a.cand FROM prop{k} a JOIN prop{k} b ON a.cand = b.n AND b.cand = a.n",
        f"win{k}": f"SELECT cand, score, n FROM (SELECT *, row_number() OVER (PARTITION BY cand ORDER BY score DESC, n DESC) AS r FROM prop{k}) WHERE r = 1",
        f"walk{k}": f"SELECT n, true AS m FROM root{k} UNION ALL SELECT n, false FROM prop{k} WHERE n NOT IN (SELECT n FROM win{k}) AND n NOT IN (SELECT n FROM root{k}) "
        f"UNION ALL SELECT w.n, NOT t.m FROM win{k} w JOIN walk{k} t ON w.cand = t.n WHERE w.n NOT IN (SELECT n FROM root{k})",
        f"mate{k}": f"SELECT DISTINCT least(p.n, p.cand) AS a, greatest(p.n, p.cand) AS b FROM prop{k} p JOIN walk{k} t ON t.n = p.n WHERE t.m",
        f"matched{k}": f"SELECT a AS n, b AS mate FROM mate{k} UNION ALL SELECT b, a FROM mate{k}",
        f"gamma{k}": f"SELECT n, least(n, coalesce(mate, n)) AS c FROM {v} LEFT JOIN matched{k} USING (n)",
        f"pins{k + 1}": f"SELECT e, c AS n, bool_or(is_src) AS is_src, bool_or(is_dst) AS is_dst FROM {p} JOIN gamma{k} USING (n) GROUP BY e, c",
        f"nodes{k + 1}": f"SELECT c AS n, sum(size)::BIGINT AS size FROM {v} JOIN gamma{k} USING (n) GROUP BY c",
    }


#: Refinement steps from a fixed assignment `assign(n, p)`.
REFINE = {
    "pe": "SELECT e, p, count(*) AS cnt, count(*) FILTER (WHERE is_dst) AS cnt_in FROM pins JOIN assign USING (n) GROUP BY e, p",
    "loads": "SELECT p, s.size, coalesce(i.inbound, 0)::BIGINT AS inbound FROM (SELECT p, sum(size)::BIGINT AS size FROM nodes JOIN assign USING (n) GROUP BY p) s "
    "LEFT JOIN (SELECT p, sum(mult)::BIGINT AS inbound FROM pe JOIN edges USING (e) WHERE cnt_in > 0 GROUP BY p) i USING (p)",
    "sav": "SELECT n, p AS ps, sum(CASE WHEN cnt = 1 THEN w ELSE 0 END)::BIGINT AS saving, sum(w)::BIGINT AS total FROM pins JOIN edges USING (e) JOIN assign USING (n) JOIN pe USING (e, p) GROUP BY n, p",
    "gain": "SELECT t.n, s.ps, t.p, (s.saving - s.total + t.touch)::BIGINT AS gain FROM (SELECT n, p, sum(w) AS touch FROM pins JOIN edges USING (e) JOIN pe USING (e) GROUP BY n, p) t JOIN sav s ON s.n = t.n WHERE t.p <> s.ps",
    "mv": "SELECT n, ps, p AS pd, gain FROM (SELECT *, row_number() OVER (PARTITION BY n ORDER BY gain DESC, p DESC) AS r FROM gain WHERE gain >= 1 AND p NOT IN (SELECT p FROM loads, lim WHERE size >= om)) WHERE r = 1",
    "seq": "SELECT row_number() OVER (ORDER BY gain DESC, n) AS idx, n, ps, pd, gain FROM mv",
    "mp": "SELECT e, s.n, w, mult, is_src, is_dst, idx, ps, pd FROM pins JOIN edges USING (e) JOIN seq s USING (n)",
    "net": "SELECT a.e, a.idx, sum((b.pd = a.ps)::INT - (b.ps = a.ps)::INT) AS a_s, sum((b.pd = a.pd)::INT - (b.ps = a.pd)::INT) AS a_d FROM mp a JOIN mp b ON a.e = b.e AND b.idx < a.idx GROUP BY a.e, a.idx",
    "side": "SELECT m.e, m.idx, w, coalesce(a_s, 0) AS a_s, coalesce(a_d, 0) AS a_d, coalesce(x.cnt, 0) AS ks, coalesce(y.cnt, 0) AS kd FROM mp m LEFT JOIN net ON net.e = m.e AND net.idx = m.idx "
    "LEFT JOIN pe x ON x.e = m.e AND x.p = m.ps LEFT JOIN pe y ON y.e = m.e AND y.p = m.pd",
    "sg": "SELECT seq.*, (gain + coalesce(ch, 0))::BIGINT AS seq_gain FROM seq LEFT JOIN (SELECT idx, sum(w * ((ks + a_s = 1)::INT - (ks = 1)::INT - (kd + a_d = 0)::INT + (kd = 0)::INT)) AS ch FROM side GROUP BY idx) USING (idx)",
    "sg_or": "SELECT seq.*, (gain + coalesce(ch, 0))::BIGINT AS seq_gain FROM seq LEFT JOIN (SELECT idx, sum(w * (((ks > 1 AND ks + a_s = 1) OR (kd = 0 AND kd + a_d > 0))::INT - ((kd > 0 AND kd + a_d = 0) OR (ks = 1 AND ks + a_s > 1))::INT)) AS ch FROM side GROUP BY idx) USING (idx)",
    "se": "SELECT p, idx, delta, sum(delta) OVER (PARTITION BY p ORDER BY idx)::BIGINT AS total FROM (SELECT ps AS p, idx, -size AS delta FROM seq JOIN nodes USING (n) UNION ALL SELECT pd, idx, size FROM seq JOIN nodes USING (n))",
    "ie": "SELECT p, e, mult, idx, delta, sum(delta) OVER (PARTITION BY p, e ORDER BY idx)::BIGINT AS total FROM (SELECT ps AS p, e, mult, idx, -1::BIGINT AS delta FROM mp WHERE is_dst UNION ALL SELECT pd, e, mult, idx, 1::BIGINT FROM mp WHERE is_dst)",
    "tr": "SELECT p, idx, delta, sum(delta) OVER (PARTITION BY p ORDER BY idx)::BIGINT AS total FROM (SELECT p, idx, sum(CASE WHEN now > 0 AND now - delta = 0 THEN mult WHEN now = 0 AND now - delta > 0 THEN -mult END)::BIGINT AS delta "
    "FROM (SELECT ie.*, coalesce(cnt_in, 0) + total AS now FROM ie LEFT JOIN pe USING (e, p)) WHERE (now > 0 AND now - delta = 0) OR (now = 0 AND now - delta > 0) GROUP BY p, idx)",
    "fl": "SELECT kind, p, idx, flip FROM (SELECT kind, p, idx, (bad - coalesce(lag(bad) OVER (PARTITION BY kind, p ORDER BY idx), bad0))::INT AS flip FROM ("
    "SELECT 'size' AS kind, se.p, idx, (coalesce(size, 0) + total > om)::INT AS bad, (coalesce(size, 0) > om)::INT AS bad0 FROM se LEFT JOIN loads USING (p), lim UNION ALL "
    "SELECT 'inbound', tr.p, idx, (coalesce(inbound, 0) + total > de)::INT, (coalesce(inbound, 0) > de)::INT FROM tr LEFT JOIN loads USING (p), lim)) WHERE flip <> 0",
    "av": "SELECT idx, (sum(coalesce(flip, 0)) OVER (ORDER BY idx) + coalesce((SELECT sum((size > om)::INT + (inbound > de)::INT) FROM loads, lim), 0))::BIGINT AS viol FROM seq LEFT JOIN (SELECT idx, sum(flip) AS flip FROM fl GROUP BY idx) USING (idx)",
    "cum": "SELECT idx, sum(seq_gain) OVER (ORDER BY idx)::BIGINT AS total FROM sg",
    "bp": "SELECT coalesce(max(idx), 0)::BIGINT AS cut, coalesce(max(total), 0)::BIGINT AS total FROM (SELECT idx, total FROM cum JOIN av USING (idx) WHERE viol = 0 AND total > 0 QUALIFY total = max(total) OVER ())",
    "app": "SELECT a.n, coalesce(s.pd, a.p) AS p FROM assign a LEFT JOIN (SELECT n, pd FROM seq, bp WHERE idx <= cut) s USING (n)",
}


def refined(k: int, assign: str) -> dict[str, str]:
    """REFINE on level k, from the partitions that the query `assign` gives its nodes: app_k has them refined."""
    named = {"assign": f"assign_{k}", "pins": f"pins{k}", "nodes": f"nodes{k}", **{n: f"{n}_{k}" for n in REFINE}}
    table = re.compile(rf"(\bFROM |\bJOIN |, )({'|'.join(named)})\b(?!\.)(?= [a-z]\b(?!\.)|( |,|\)|$))(?! OVER)")

    def own(m: re.Match) -> str:
        # a table without an alias of its own keeps its name as alias
        return m[1] + named[m[2]] + (f" {m[2]}" if m[3] is not None else "")

    def renamed(sql: str) -> str:
        out, at = [], 0
        for m in table.finditer(sql):
            # after a comma only in lists of tables, not of columns
            if m[1] == ", " and not re.search(r"\bFROM [^()]*$", sql[: m.start()]):
                continue
            out += [sql[at : m.start()], own(m)]
            at = m.end(2)
        return "".join([*out, sql[at:]])

    return {f"assign_{k}": assign} | {f"{n}_{k}": renamed(sql) for n, sql in REFINE.items()}


def multilevel(name: str, levels: int) -> dict[str, str]:
    """The whole method over so many levels, unrolled: app_0 has the partitions."""
    ctes = graph(name, levels) | refined(levels, f"SELECT n, n AS p FROM nodes{levels}")
    for k in range(levels - 1, -1, -1):
        ctes |= refined(k, f"SELECT g.n, a.p FROM gamma{k} g JOIN app_{k + 1} a ON a.n = g.c")
    return ctes


def one_pass(name: str, width: int | None = None) -> str:
    """The one-pass filler as a recursion over nodes by id; over ranges of `width` ids if given."""
    block = f"n // {width}" if width else "0"
    ctes = graph(name, 0) | {
        "ord": f"SELECT n, size, {block} AS blk, row_number() OVER (ORDER BY n) AS i, coalesce(es, []) AS es FROM nodes LEFT JOIN (SELECT n, list(e) AS es FROM pins WHERE is_dst GROUP BY n) USING (n)",
        "walk0": "SELECT i, n, n AS p, size, es AS held, blk FROM ord WHERE i = 1 UNION ALL "
        "SELECT o.i, o.n, CASE WHEN f THEN p ELSE o.n END, CASE WHEN f THEN w.size + o.size ELSE o.size END, CASE WHEN f THEN u ELSE o.es END, o.blk "
        "FROM (SELECT w.*, list_distinct(list_concat(w.held, o.es)) AS u, o.blk = w.blk AND w.size + o.size <= om AND len(u) <= de AS f FROM walk0 w JOIN ord o ON o.i = w.i + 1, lim) w JOIN ord o ON o.i = w.i + 1",
    }
    return compose(ctes, "SELECT n, p FROM walk0")


def compose(ctes: dict[str, str], final: str) -> str:
    """WITH the expressions that final needs, in order."""
    need, todo = set(), {final}
    while todo:
        text = todo.pop()
        for name in ctes:
            if name not in need and re.search(rf"\b{name}\b", text):
                need.add(name)
                todo.add(ctes[name])
    once = lambda n: "" if re.match(r"walk\d", n) else " MATERIALIZED"
    head = ", ".join(f"{n} AS{once(n)} ({ctes[n]})" for n in ctes if n in need)
    return f"WITH RECURSIVE {head} {final}" if head else final


def graph(name: str, levels: int = 3, bound: str = "is_dst", assign: str | None = None) -> dict[str, str]:
    ctes = workload_ctes(name) | {"lim": limit_cte(name), "pins0": "SELECT * FROM pins", "nodes0": "SELECT * FROM nodes"}
    for k in range(levels):
        ctes |= level_ctes(k, bound)
    if assign:
        ctes |= {"assign": assign} | REFINE
    return ctes
