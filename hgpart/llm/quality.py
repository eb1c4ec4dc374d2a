"""Quality rules: distribution divergence against language references, in SQL functions only.

A document's histogram over character classes and its histogram over the ten commonest words of its language
(plus all other words) are compared with that language's references by the Jensen-Shannon distance. Short
texts scatter more, so a limit grows with 1/sqrt(length), and below the minimum length the base rules decide alone.

The references are shares measured on the 3,243 documents labelled as good of the 10,000 of one small table (the bound of
the sample); they are part of the program, and the rules behave alike at every size.

Edge cases: a null text counts as empty (no words, base_failed), an unknown or null language is held against the
mean class reference only, ties and repeated rows are judged row by row, texts may be of any length, an empty
table gives an empty result, further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.llm.tables import lean_parser

#: Shares of lower-case letters, capitals, digits, white space, punctuation, symbols in good prose by language.
CLASS_SHARES = {
    "en": [0.7952, 0.0138, 0.0005, 0.1667, 0.0237, 0.0001],
    "de": [0.8103, 0.0128, 0.0004, 0.1546, 0.0218, 0.0001],
    "fr": [0.7946, 0.014, 0.0008, 0.1667, 0.0238, 0.0001],
    "es": [0.8011, 0.0134, 0.0007, 0.1617, 0.023, 0.0001],
}
#: The same over all four languages.
ANY_CLASS_SHARES = [0.798, 0.0136, 0.0006, 0.1644, 0.0233, 0.0001]
#: The commonest words of each language.
COMMON_WORDS = {
    "en": ["the", "of", "and", "to", "a", "in", "is", "that", "it", "for"],
    "de": ["der", "die", "und", "in", "den", "von", "zu", "das", "mit", "sich"],
    "fr": ["de", "la", "le", "et", "les", "des", "en", "un", "du", "une"],
    "es": ["de", "la", "que", "el", "en", "y", "los", "se", "del", "un"],
}
#: Their shares of all words; the rest is that of all other words.
WORD_SHARES = {
    "en": [0.0629, 0.0365, 0.0264, 0.02, 0.0158, 0.0139, 0.0117, 0.0106, 0.0094, 0.0085],
    "de": [0.0622, 0.0366, 0.0262, 0.02, 0.0162, 0.0136, 0.0111, 0.0109, 0.0093, 0.0084],
    "fr": [0.0625, 0.0378, 0.0253, 0.0208, 0.0164, 0.0139, 0.0125, 0.0108, 0.0091, 0.008],
    "es": [0.0623, 0.0364, 0.0256, 0.0199, 0.0163, 0.0137, 0.0117, 0.0103, 0.0092, 0.0081],
}
#: Limits of the distances: base + slack / sqrt(length).
CLASS_LIMIT, CLASS_SLACK = 0.16, 1.2
WORD_LIMIT, WORD_SLACK = 0.2, 0.5
MIN_WORDS = 50

_CAPITALS = "ABCDEFGHIJKLMNOPQRSTUVWXYZÀÁÂÃÄÅÆÇÈÉÊËÌÍÎÏÑÒÓÔÕÖØÙÚÛÜÝ"
_SPACES = " \t\n\x0b\x0c\r"
_SYMBOLS = "#*$%&|<>"
_OTHER_SYMBOLS = "@=+/\\_[]{}^~`"
_PUNCTUATION = ".,;:!?'\"()-"
_DIGITS = "0123456789"
_WORD_BREAK = r"[\x20\x09-\x0D]+"


def _q(text: str) -> str:
    """A SQL string literal."""
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'").replace("\n", "\\n").replace("\r", "\\r").replace("\t", "\\t") + "'"


def with_rest(shares: list[float]) -> list[float]:
    return [*shares, round(1 - sum(shares), 4)]


def _by_language(references: dict[str, list[float]], other: list[float]) -> str:
    """SQL of the reference of a row's language."""
    array = lambda shares: "array(" + ", ".join(f"{x!r}D" for x in shares) + ")"
    return "CASE " + " ".join(f"WHEN lang = {_q(lang)} THEN {array(x)}" for lang, x in references.items()) + f" ELSE {array(other)} END"


def _distance(counts: list[str], total: str, reference: str) -> str:
    """SQL of the Jensen-Shannon distance (base 2) between counts / total and the shares in the array `reference`."""
    terms = []
    for k, c in enumerate(counts):
        p, s = f"({c} / {total})", f"{reference}[{k}]"
        m = f"(({p} + {s}) / 2)"
        terms.append(f"(CASE WHEN {c} > 0 THEN {p} * log2({p} / {m}) ELSE 0D END + {s} * log2({s} / {m})) / 2")
    return "sqrt(greatest(0D, " + " + ".join(terms) + "))"


@lean_parser
def measure(docs: DataFrame) -> DataFrame:
    """Every row of docs with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
    class_distance, word_distance and kept appended (the engine's columns win over clashing names)."""
    new = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "class_distance", "word_distance", "kept"]
    carried = [c for c in docs.columns if c not in new and not c.startswith("q__")]
    keep = [F.col(f"`{c}`") for c in carried]
    to = "A" * len(_CAPITALS) + " " * len(_SPACES) + "#" * len(_SYMBOLS) + "@" * len(_OTHER_SYMBOLS) + "." * len(_PUNCTUATION) + "0" * len(_DIGITS)
    mapped = f"translate(q__t, {_q(_CAPITALS + _SPACES + _SYMBOLS + _OTHER_SYMBOLS + _PUNCTUATION + _DIGITS)}, {_q(to)})"
    strip = ".,;:!?\"()"
    union = sorted({w for words in COMMON_WORDS.values() for w in words})
    step = docs.select(*keep, F.expr("coalesce(text, '')").alias("q__t"))
    step = step.select(
        *keep,
        "q__t",
        F.expr(f"filter(split(q__t, {_q(_WORD_BREAK)}), w -> w <> '')").alias("q__w"),
        F.expr(f"filter(split(lower(translate(q__t, {_q(strip)}, '')), {_q(_WORD_BREAK)}), w -> w IN ({', '.join(map(_q, union))}))").alias("q__c"),
        F.expr(f"filter(split(q__t, '\\n'), l -> l rlike {_q(r'[^\x20\x09-\x0D]')})").alias("q__lines"),
        F.expr(mapped).alias("q__m"),
    )
    share = lambda mark: f"(q__len - length(replace(q__m, {_q(mark)}, '')))"
    step = step.select(
        *keep,
        "q__w",
        "q__c",
        F.expr("cast(size(q__w) as bigint)").alias("n_words"),
        F.expr("cast(size(q__lines) - size(array_distinct(q__lines)) as bigint)").alias("n_dup_lines"),
        F.col("q__m"),
        F.expr("length(q__t)").alias("q__len"),
        # as many bits as positions need; the rest of a long takes a hash: sorted as plain longs, equal windows meet
        F.expr("length(bin(size(q__w)))").alias("q__b"),
    ).withColumn(
        "q__s",
        F.expr(
            "CASE WHEN size(q__w) >= 3 THEN sort_array(transform(sequence(0, size(q__w) - 3), "
            "i -> shiftleft(xxhash64(q__w[i], q__w[i + 1], q__w[i + 2]), q__b) | cast(i as bigint))) ELSE cast(array() as array<bigint>) END"
        ),
    )
    step = step.select(
        *keep,
        "q__w",
        "q__c",
        "q__b",
        "n_words",
        "n_dup_lines",
        F.expr(f"cast({share('A')} as bigint)").alias("q__up"),
        F.expr(f"cast({share('0')} as bigint)").alias("q__dig"),
        F.expr(f"cast({share(' ')} as bigint)").alias("q__ws"),
        F.expr(f"cast({share('.')} as bigint)").alias("q__pun"),
        F.expr(f"cast({share('#')} as bigint)").alias("n_symbols"),
        F.expr(f"cast({share('@')} as bigint)").alias("q__sym"),
        F.expr("cast(q__len as bigint)").alias("q__len"),
        F.expr(
            "transform(filter(q__s, (x, k) -> (k > 0 AND shiftright(get(q__s, k - 1), q__b) = shiftright(x, q__b)) "
            "OR (k < size(q__s) - 1 AND shiftright(get(q__s, k + 1), q__b) = shiftright(x, q__b))), x -> cast(x & (shiftleft(1L, q__b) - 1) as int))"
        ).alias("q__s"),
    )
    # windows whose hashes meet are compared word by word
    step = step.withColumn(
        "q__v",
        F.expr(
            "array_sort(transform(q__s, x -> struct(concat_ws(' ', q__w[x], q__w[x + 1], q__w[x + 2]) as t, x as p)))"
        ),
    )
    step = step.withColumn(
        "q__p",
        F.expr(
            "sort_array(transform(filter(q__v, (x, k) -> (k > 0 AND get(q__v, k - 1).t = x.t) OR (k < size(q__v) - 1 AND get(q__v, k + 1).t = x.t)), x -> x.p))"
        ),
    )
    step = step.withColumn(
        "n_repeat_words",
        F.expr("aggregate(q__p, struct(0L as n, 0 as to), (s, p) -> struct(s.n + p + 3 - greatest(p, s.to) as n, p + 3 as to), s -> s.n)"),
    )
    word_counts = {
        lang: [f"size(filter(q__c, w -> w = {_q(w)}))" for w in words] for lang, words in COMMON_WORDS.items()
    }
    ranked = [
        F.expr("CASE " + " ".join(f"WHEN lang = {_q(lang)} THEN {counts[k]}" for lang, counts in word_counts.items()) + " ELSE 0 END").alias(f"q__w{k}")
        for k in range(10)
    ]
    lang_known = "lang IN (" + ", ".join(map(_q, COMMON_WORDS)) + ")" if "lang" in docs.columns else "false"
    references = [F.expr(_by_language(CLASS_SHARES, ANY_CLASS_SHARES)), F.expr(_by_language({k: with_rest(x) for k, x in WORD_SHARES.items()}, with_rest(WORD_SHARES["en"])))]
    if "lang" not in docs.columns:
        ranked = [F.lit(0).alias(f"q__w{k}") for k in range(10)]
        references = [F.array(*map(F.lit, ANY_CLASS_SHARES)), F.array(*map(F.lit, with_rest(WORD_SHARES["en"])))]
    step = step.select(
        *keep,
        "n_words",
        F.expr("q__len - q__ws").alias("word_chars"),
        "n_symbols",
        "n_dup_lines",
        "n_repeat_words",
        F.expr("n_words < 50 OR 100 * n_repeat_words > 50 * n_words").alias("base_failed"),
        "q__up",
        "q__dig",
        "q__ws",
        "q__pun",
        F.expr("n_symbols + q__sym").alias("q__sym"),
        F.expr("q__len - q__up - q__dig - q__ws - q__pun - n_symbols - q__sym").alias("q__low"),
        "q__len",
        *ranked,
        references[0].alias("q__cr"),
        references[1].alias("q__wr"),
    )
    w_other = "(n_words - (" + " + ".join(f"q__w{k}" for k in range(10)) + "))"
    class_d = _distance(["q__low", "q__up", "q__dig", "q__ws", "q__pun", "q__sym"], "cast(q__len as double)", "q__cr")
    word_d = _distance([f"q__w{k}" for k in range(10)] + [f"greatest(0, {w_other})"], "cast(n_words as double)", "q__wr")
    step = step.withColumn("class_distance", F.expr(f"CASE WHEN n_words >= {MIN_WORDS} THEN {class_d} END")).withColumn(
        "word_distance", F.expr(f"CASE WHEN n_words >= {MIN_WORDS} AND coalesce({lang_known}, false) THEN {word_d} END")
    )
    verdict = (
        f"NOT base_failed AND NOT coalesce(class_distance > {CLASS_LIMIT} + {CLASS_SLACK} / sqrt(cast(q__len as double)), false) "
        f"AND NOT coalesce(word_distance > {WORD_LIMIT} + {WORD_SLACK} / sqrt(cast(n_words as double)), false)"
    )
    return step.select(*keep, *new[:-1], F.expr(verdict).alias("kept"))


def quality_report(docs: DataFrame) -> DataFrame:
    return measure(docs.select("doc_id", "text", "lang")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def keep_good(docs: DataFrame) -> DataFrame:
    """docs without the rows that the rules reject; columns as given."""
    # a filter on a row number stays above the projections; pushed into them it would repeat all their work
    return measure(docs).withColumn("q__row", F.monotonically_increasing_id()).filter("kept AND q__row >= 0").select(*[F.col(f"`{c}`") for c in docs.columns])
