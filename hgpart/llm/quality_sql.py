"""The quality report in DuckDB SQL, over documents with unique ids."""

from __future__ import annotations

from hgpart.llm import quality as q


def _lit(text: str) -> str:
    """A SQL string; control characters as chr()."""
    out, run = [], ""
    for c in text:
        if ord(c) < 32:
            out += [f"'{run}'", f"chr({ord(c)})"]
            run = ""
        else:
            run += "''" if c == "'" else c
    return "(" + " || ".join([*out, f"'{run}'"]) + ")"


def _distance(counts: list[str], total: str, reference: str) -> str:
    terms = []
    for k, c in enumerate(counts, 1):
        p, s = f"({c})::DOUBLE / {total}", f"{reference}[{k}]"
        m = f"(({p} + {s}) / 2)"
        terms.append(f"(CASE WHEN {c} > 0 THEN {p} * log2({p} / {m}) ELSE 0 END + {s} * log2({s} / {m})) / 2")
    return f"sqrt(greatest(0, {' + '.join(terms)}))"


def _by_language(references: dict[str, list[float]], other: list[float]) -> str:
    array = lambda shares: "[" + ", ".join(f"{x}::DOUBLE" for x in shares) + "]"
    return "CASE lang " + " ".join(f"WHEN '{lang}' THEN {array(x)}" for lang, x in references.items()) + f" ELSE {array(other)} END"


def report_sql() -> str:
    sources = q._CAPITALS + q._SPACES + q._SYMBOLS + q._OTHER_SYMBOLS + q._PUNCTUATION + q._DIGITS
    marks = "A" * len(q._CAPITALS) + " " * len(q._SPACES) + "#" * len(q._SYMBOLS) + "@" * len(q._OTHER_SYMBOLS) + "." * len(q._PUNCTUATION) + "0" * len(q._DIGITS)
    space = r"'[\x20\x09-\x0D]+'"
    share = lambda mark: f"(length(m) - length(replace(m, '{mark}', '')))"
    words = ", ".join(
        "CASE lang " + " ".join(f"WHEN '{lang}' THEN len(list_filter(c, lambda x: x = '{ws[k]}'))" for lang, ws in q.COMMON_WORDS.items()) + f" ELSE 0 END AS w{k}" for k in range(10)
    )
    known = ", ".join(f"'{lang}'" for lang in q.COMMON_WORDS)
    class_d = _distance(["low", "up", "dig", "sp", "pun", "n_symbols + sym"], "len", "cr")
    word_d = _distance([f"w{k}" for k in range(10)] + ["greatest(0, n_words - (" + " + ".join(f"w{k}" for k in range(10)) + "))"], "n_words", "wr")
    return f"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS t, lang FROM documents),
w AS MATERIALIZED (SELECT doc_id, t, lang, list_filter(string_split_regex(t, {space}), lambda x: x <> '') AS ws,
  string_split_regex(lower(translate(t, '.,;:!?"()', '')), {space}) AS c, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS ls,
  translate(t, {_lit(sources)}, '{marks}') AS m FROM t),
u AS (SELECT doc_id, unnest(ws) AS a, generate_subscripts(ws, 1) AS i FROM w),
g AS (SELECT doc_id, i, a, lead(a) OVER (PARTITION BY doc_id ORDER BY i) AS b, lead(a, 2) OVER (PARTITION BY doc_id ORDER BY i) AS d FROM u),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, a, b, d) AS k FROM g WHERE d IS NOT NULL) WHERE k > 1),
v AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS j FROM r) GROUP BY doc_id),
s AS (SELECT doc_id, lang, len(ws) AS n_words, length(t) - {share(' ')} AS word_chars, {share('#')} AS n_symbols, len(ls) - len(list_distinct(ls)) AS n_dup_lines, coalesce(v.n, 0) AS n_repeat_words,
  length(t) AS len, {share('A')} AS up, {share('0')} AS dig, {share(' ')} AS sp, {share('.')} AS pun, {share('@')} AS sym, {words} FROM w LEFT JOIN v USING (doc_id)),
f AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, len - up - dig - sp - pun - n_symbols - sym AS low,
  {_by_language(q.CLASS_SHARES, q.ANY_CLASS_SHARES)} AS cr, {_by_language({k: q.with_rest(x) for k, x in q.WORD_SHARES.items()}, q.with_rest(q.WORD_SHARES['en']))} AS wr FROM s),
d AS (SELECT *, CASE WHEN n_words >= {q.MIN_WORDS} THEN {class_d} END AS cd, CASE WHEN n_words >= {q.MIN_WORDS} AND lang IN ({known}) THEN {word_d} END AS wd FROM f)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND NOT coalesce(cd > {q.CLASS_LIMIT} + {q.CLASS_SLACK} / sqrt(len), false) AND NOT coalesce(wd > {q.WORD_LIMIT} + {q.WORD_SLACK} / sqrt(n_words), false) AS kept
FROM d
"""
