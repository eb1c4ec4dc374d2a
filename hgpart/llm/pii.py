"""Surrogates for personal data and secrets, in SQL functions only.

Each detected entity gets a replacement of its own kind, derived from a keyed hash of its
normalised form: addresses stay addresses, card numbers keep their length and a valid check digit, account numbers
(IBAN) their country, layout and valid check digits, phone numbers their country code and punctuation, social security
numbers stay among those that can be issued. Names are replaced part by part, the surname by a surname of its script, the
given name by one of its script and gender, so a person met with and without given name or title keeps one surname.
Equal entities get equal surrogates everywhere (coreference). Surrogates are checked over
the whole corpus: one that two entities share, or that is itself an original, is drawn again for all but the
first, until none is left (distinctness); a kind with too few values for its entities raises.

Names are found by a title, or by a common given name before a capitalised word; others are not searched for.

Edge cases: a null text stays null, an empty one empty; a null key column does no harm; repeated rows are
rewritten alike; an empty table gives an empty result; further columns pass through unchanged, n_chars is
brought up to date where present. Names that start with pii__ are the operator's own.
"""

from __future__ import annotations

import secrets
from functools import lru_cache, reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hgpart.llm.tables import lean_parser, written

#: Session setting that holds the secret key; without it each program draws its own, and its surrogates cannot be linked to another's.
KEY_SETTING = "spark.hgpart.surrogateKey"
#: Rounds of drawing again after which a kind is taken to have too few values.
MAX_ROUNDS = 64
#: Redrawn entities a task may hold; beyond it they are joined by shuffle.
BROADCAST_ROWS = 20_000

#: Titles with their gender.
TITLES = {
    "m": ["Mr", "Herr", "Monsieur", "Señor", "Sr", "г-н", "κ\\."],
    "f": ["Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Señora", "Sra", "г-жа", "κα\\."],
}
#: Given names by script and gender.
GIVEN = {
    "latin": {"m": ["Adam", "Bruno", "Carl", "David", "Emil", "Felix", "Henri", "Ivan", "Jonas", "Leo", "Martin", "Oscar", "Paul", "Simon", "Tomas", "Victor"],
              "f": ["Anna", "Berta", "Clara", "Diana", "Elena", "Flora", "Greta", "Irene", "Julia", "Laura", "Maria", "Nora", "Paula", "Rosa", "Sofia", "Vera"]},
    "cyrillic": {"m": ["Антон", "Борис", "Виктор", "Глеб", "Денис", "Егор", "Иван", "Кирилл"], "f": ["Анна", "Вера", "Галина", "Дарья", "Елена", "Ирина", "Мария", "Ольга"]},
    "greek": {"m": ["Νίκος", "Πέτρος", "Άρης", "Λουκάς"], "f": ["Άννα", "Ελένη", "Μαρία", "Σοφία"]},
}
#: Common given names, by which names without a title are found.
KNOWN = {
    "m": ["James", "John", "Robert", "Michael", "William", "David", "Richard", "Joseph", "Thomas", "Charles", "Daniel", "Matthew", "Anthony", "Paul", "Steven", "Andrew", "George", "Peter", "Hans", "Klaus", "Jürgen",
          "Wolfgang", "Stefan", "Jean", "Pierre", "Michel", "Philippe", "Jacques", "José", "Juan", "Carlos", "Luis", "Miguel", "Javier", "Martin"],
    "f": ["Mary", "Patricia", "Jennifer", "Linda", "Elizabeth", "Barbara", "Susan", "Jessica", "Sarah", "Karen", "Nancy", "Lisa", "Margaret", "Sandra", "Emily", "Anna", "Maria", "Ursula", "Monika", "Petra", "Sabine",
          "Claudia", "Marie", "Isabelle", "Nathalie", "Sophie", "Carmen", "Ana", "Lucía", "Laura", "Isabel", "Jane", "Alice", "Julia"],
}
#: Syllables of surrogate names by script.
SYLLABLES = {
    "latin": ["ba", "co", "da", "fe", "ga", "hu", "ki", "la", "mo", "na", "po", "ri", "sa", "te", "vu", "wi"],
    "cyrillic": ["ба", "во", "га", "де", "жи", "ка", "ло", "ми", "на", "по", "ра", "се", "ту", "фи", "хо", "ча"],
    "greek": ["βα", "γο", "δα", "ζε", "θα", "κι", "λο", "μα", "νο", "πα", "ρι", "σα", "το", "φε", "χα", "ψι"],
}
#: Endings of surrogate given names by script and gender.
ENDINGS = {"latin": {"m": "us", "f": "a"}, "cyrillic": {"m": "ин", "f": "а"}, "greek": {"m": "ος", "f": "α"}}
_TITLE = "|".join(t for titles in TITLES.values() for t in titles)
_KNOWN = "|".join(n for names in KNOWN.values() for n in names)
#: Patterns of the kinds, tried in this order.
PATTERNS = {
    "key": r"\bAKIA[A-Z0-9]{16}\b",
    "secret": r"(?i:\b(?:password|passwd|pwd|secret|token|api[_-]?key|access[_-]?key)\b\s?[=:]\s?[\"']?)[A-Za-z0-9+/_-]{8,}",
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9][A-Za-z0-9._%+-]*+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}",
    "ip": r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?!\.?\d)",
    "iban": r"\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?\b",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "phone": r"(?<![\w+])(?:\+\d{1,3}[ .-]?)?\(\d{2,4}\)[ .-]?\d{3,4}[ .-]?\d{3,4}(?!\d)|(?<![\w+])\+\d{1,3}(?:[ .-]?\d{2,4}){2,5}(?!\d)|(?<![\d.+-])\d{3}[.-]\d{3}[.-]\d{4}(?![\d-])|(?<![\d.+-])\d{3}-\d{4}(?![\d-])",
    "card": r"(?<![\d.])(?:\d{13,19}|\d{4}(?:[ -]\d{4}){3})(?![\d.]?\d)",
    "name": rf"\b(?:{_TITLE})\.? \p{{Lu}}\p{{L}}+(?: \p{{Lu}}\p{{L}}+)?|\b(?=\p{{Lu}})(?:{_KNOWN}) \p{{Lu}}\p{{L}}+",
}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: A key holds AKIA and may be all letters; every other entity but a name has one of these characters; every name
#: starts like this. Texts with none of these are not searched.
GATE = "[0-9@=:]|AKIA"
NAME_GATE = rf"[MHFSгκ](?:r|rs|s|iss|onsieur|adame|me|err|rau|eñor|eñora|ra|-н|-жа|\.|α\.)\.? \p{{Lu}}|\b(?=\p{{Lu}})(?:{_KNOWN}) \p{{Lu}}"


def _q(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _kind(e: str) -> str:
    cases = " ".join(f"WHEN {e} rlike {_q('^(?:' + p + ')$')} THEN {_q(k)}" for k, p in PATTERNS.items() if k != 'name')
    return f"CASE {cases} ELSE 'name' END"


def _digits(e: str) -> str:
    return f"regexp_replace({e}, '\\\\D', '')"


def _core(e: str, kind: str) -> str:
    """What of the entity is replaced: the value of a secret, the surname of a name, else all of it."""
    return f"CASE WHEN {kind} = 'secret' THEN regexp_extract({e}, '([A-Za-z0-9+/_-]+)$', 1) WHEN {kind} = 'name' THEN regexp_extract({e}, '(\\\\S+)$', 1) ELSE {e} END"


def _normal(core: str, kind: str) -> str:
    return (
        f"CASE WHEN {kind} = 'email' OR {kind} = 'name' OR {kind} LIKE 'given%' THEN lower({core}) WHEN {kind} IN ('phone', 'card', 'ssn') THEN {_digits(core)} "
        f"WHEN {kind} = 'iban' THEN replace({core}, ' ', '') ELSE {core} END"
    )


def _title(e: str) -> str:
    return f"CASE WHEN {e} rlike {_q('^(?:' + _TITLE + ')[. ]')} THEN regexp_extract({e}, '^(\\\\S+ )', 1) ELSE '' END"


def _gender(e: str, given: str) -> str:
    """m, f or x: of the title, else of the given name."""
    titled = " ".join(f"WHEN {e} rlike {_q('^(?:' + '|'.join(t) + ')[. ]')} THEN '{g}'" for g, t in TITLES.items())
    known = " ".join(f"WHEN {given} IN ({', '.join(map(_q, n))}) THEN '{g}'" for g, n in KNOWN.items())
    return f"CASE {titled} {known} ELSE 'x' END"


def _byte(h: str, i: str) -> str:
    return f"cast(conv(substr({h}, 2 * (({i}) % 64) + 1, 2), 16, 10) as int)"


def _letters(s: str, h: str, keep: int = 0) -> str:
    """s with digits and letters drawn anew, case kept; the first `keep` characters stay."""
    c, v = f"substr({s}, i, 1)", _byte(h, "i")
    return (
        f"CASE WHEN length({s}) = 0 THEN '' ELSE array_join(transform(sequence(1, length({s})), i -> CASE WHEN i <= {keep} THEN {c} "
        f"WHEN {c} rlike '[0-9]' THEN cast({v} % 10 as string) WHEN {c} rlike '[a-z]' THEN char(97 + {v} % 26) "
        f"WHEN {c} rlike '[A-Z]' THEN char(65 + {v} % 26) ELSE {c} END), '') END"
    )


def _hex(s: str, h: str) -> str:
    c, v = f"substr({s}, i, 1)", _byte(h, "i")
    return f"array_join(transform(sequence(1, length({s})), i -> CASE WHEN {c} rlike '[0-9]' THEN cast({v} % 10 as string) ELSE char(97 + {v} % 6) END), '')"


def _refill(e: str, new: str, places: str = "[0-9]") -> str:
    """e with the characters at `places` replaced in order by those of `new`."""
    return (
        f"aggregate(transform(sequence(1, length({e})), i -> substr({e}, i, 1)), struct('' as o, 0 as k), "
        f"(s, c) -> CASE WHEN c rlike '{places}' THEN struct(concat(s.o, substr({new}, s.k + 1, 1)) as o, s.k + 1 as k) "
        f"ELSE struct(concat(s.o, c) as o, s.k as k) END, s -> s.o)"
    )


def _iban(e: str, h: str) -> str:
    """Country and layout of e, an account drawn anew, and the check digits that make the whole 1 modulo 97."""
    drawn = _letters(f"replace({e}, ' ', '')", h, 4)
    rest = "aggregate(transform(sequence(1, length(pii__v)), i -> ascii(substr(pii__v, i, 1))), 0, (r, c) -> CASE WHEN c < 58 THEN (r * 10 + c - 48) % 97 ELSE (r * 100 + c - 55) % 97 END)"
    whole = f"transform(array(concat(substr(pii__b, 5), substr(pii__b, 1, 2), '00')), pii__v -> concat(substr(pii__b, 1, 2), lpad(cast(98 - {rest} as string), 2, '0'), substr(pii__b, 5)))[0]"
    return f"transform(array({drawn}), pii__b -> transform(array({whole}), pii__w -> {_refill(e, 'pii__w', '[^ ]')})[0])[0]"


def _ssn(e: str, h: str) -> str:
    """Areas 001 to 899 but 666, groups and serials from 1."""
    two = lambda k: f"(256 * {_byte(h, str(k))} + {_byte(h, str(k + 1))})"
    area = f"transform(array(1 + {two(0)} % 898), a -> a + cast(a >= 666 as int))[0]"
    digits = f"concat(lpad(cast({area} as string), 3, '0'), lpad(cast(1 + {two(2)} % 99 as string), 2, '0'), lpad(cast(1 + {two(4)} % 9999 as string), 4, '0'))"
    return f"transform(array({digits}), pii__w -> {_refill(e, 'pii__w')})[0]"


def _new_digits(n: str, h: str, keep: str) -> str:
    c, v = f"substr({n}, i, 1)", _byte(h, "i")
    return (
        f"array_join(transform(sequence(1, length({n})), i -> CASE WHEN i <= {keep} THEN {c} "
        f"WHEN i = {keep} + 1 THEN cast(2 + {v} % 8 as string) ELSE cast({v} % 10 as string) END), '')"
    )


def _checked(body: str) -> str:
    """body with its check digit (doubling every second digit from the right)."""
    d = f"cast(substr({body}, length({body}) - i + 1, 1) as int)"
    total = f"aggregate(transform(sequence(1, length({body})), i -> CASE WHEN i % 2 = 1 THEN (2 * {d}) div 10 + (2 * {d}) % 10 ELSE {d} END), 0, (a, x) -> a + cast(x as int))"
    return f"concat({body}, cast((10 - {total} % 10) % 10 as string))"


def _by_script(e: str, of: dict[str, str]) -> str:
    return f"CASE WHEN {e} rlike '\\\\p{{IsCyrillic}}' THEN {of['cyrillic']} WHEN {e} rlike '\\\\p{{IsGreek}}' THEN {of['greek']} ELSE {of['latin']} END"


def name_sql(e: str, kind: str, normal: str, attempt: str, key: str) -> str:
    """SQL of the replacement of a surname (kind is the literal 'name') or of a given name (kind is given_m, given_f or given_x)."""
    h, arr = "pii__h", lambda words: "array(" + ", ".join(map(_q, words)) + ")"
    draw = f"sha2(concat({_q(key)}, '|', {kind}, '|', {normal}, '|', {attempt}), 512)"
    syllables = _by_script(e, {script: arr(x) for script, x in SYLLABLES.items()})
    made = lambda n: f"array_join(transform(sequence(1, {n}), i -> element_at(pii__s, 1 + {_byte(h, 'i + 2')} % size(pii__s))), '')"
    of_gender = lambda g, m, f, x: f"CASE WHEN {kind} = 'given_m' THEN {m} WHEN {kind} = 'given_f' THEN {f} ELSE {x} END"
    listed = _by_script(e, {script: of_gender(kind, arr(x["m"]), arr(x["f"]), arr(x["m"] + x["f"])) for script, x in GIVEN.items()})
    ending = _by_script(e, {script: of_gender(kind, _q(x["m"]), _q(x["f"]), "''") for script, x in ENDINGS.items()})
    if kind == "'name'":
        out = f"initcap({made('6')})"
    else:
        out = (
            f"CASE WHEN {attempt} = 0 THEN transform(array({listed}), pii__l -> element_at(pii__l, 1 + {_byte(h, '1')} % size(pii__l)))[0] "
            f"ELSE initcap(concat({made(f'1 + least({attempt}, 12)')}, {ending})) END"
        )
    return f"transform(array({draw}), {h} -> transform(array({syllables}), pii__s -> {out})[0])[0]"


def surrogate_sql(e: str, kind: str, normal: str, attempt: str, key: str) -> str:
    """SQL of the replacement of entity e, names apart, of a kind given as a literal; the 512 hash bits come in through a one-element transform
    so that they are drawn once."""
    h = "pii__h"
    draw = f"sha2(concat({_q(key)}, '|', {kind}, '|', {normal}, '|', {attempt}), 512)"
    phone_keep = f"length(regexp_extract({e}, '^\\\\+(\\\\d{{1,3}})(?:\\\\D|$)', 1))"
    card = _digits(e)
    body = f"substr({_new_digits(card, h, '1')}, 1, length({card}) - 1)"
    at = f"instr({e}, '@')"
    tld = f"regexp_extract({e}, '(\\\\.[A-Za-z]+)$', 1)"
    domain = f"substr({e}, {at} + 1, length({e}) - {at} - length({tld}))"
    lower_local = f"substr({normal}, 1, {at} - 1)"
    octets = "concat_ws('.', " + ", ".join(f"cast(1 + (256 * {_byte(h, str(2 * k))} + {_byte(h, str(2 * k + 1))}) % 254 as string)" for k in range(4)) + ")"
    shifted = f"concat(substr({h}, 65), substr({h}, 1, 64))"
    cases = {
        "key": f"concat('AKIA', substr({_letters(e, h)}, 5))",
        "secret": f"CASE WHEN {e} rlike '^[0-9a-f]+$' THEN {_hex(e, h)} ELSE {_letters(e, h)} END",
        "email": f"concat({_letters(lower_local, h)}, '@', {_letters(f'lower({domain})', shifted)}, lower({tld}))",
        "ip": octets,
        "iban": _iban(e, h),
        "ssn": _ssn(e, h),
        "phone": _refill(e, _new_digits(_digits(e), h, phone_keep)),
        "card": _refill(e, _checked(body)),
    }
    return f"transform(array({draw}), {h} -> {cases[kind.strip(chr(39))]})[0]"


def _found(docs: DataFrame) -> DataFrame:
    """docs with pii__parts and pii__all: the text cut at its entities, and these in order.

    An entity has what is replaced (w) and its normal form; a name also its title, its given name and that one's kind."""
    hit = f"text rlike {_q(GATE)} OR text rlike {_q(NAME_GATE)}"
    named = "CASE WHEN x.kind = 'name' THEN {} ELSE '' END"
    steps = [
        f"transform(pii__e, e -> struct(e as e, {_kind('e')} as kind))",
        f"transform(pii__all, x -> struct(x.e as e, x.kind as kind, {_core('x.e', 'x.kind')} as w, {named.format(_title('x.e'))} as title))",
        f"transform(pii__all, x -> struct(x.e as e, x.kind as kind, x.w as w, {_normal('x.w', 'x.kind')} as normal, x.title as title, {named.format('trim(substr(x.e, length(x.title) + 1, length(x.e) - length(x.title) - length(x.w)))')} as given))",
        f"transform(pii__all, x -> struct(x.e as e, x.kind as kind, x.w as w, x.normal as normal, x.title as title, x.given as given, CASE WHEN x.given <> '' THEN concat('given_', {_gender('x.e', 'x.given')}) ELSE '' END as gkind))",
    ]
    rows = docs.withColumn("pii__e", F.expr(f"CASE WHEN {hit} THEN regexp_extract_all(text, {_q(ANY)}, 0) ELSE cast(array() as array<string>) END"))
    for step in steps:
        rows = rows.withColumn("pii__all", F.expr(step))
    return rows.withColumn("pii__parts", F.expr(f"CASE WHEN size(pii__e) > 0 THEN split(text, {_q(ANY)}, -1) END")).drop("pii__e")


#: What is drawn for each entity of a text: it, and the given name of a name.
_DRAWN = "concat(transform(pii__all, x -> struct(x.kind as kind, x.normal as normal, x.w as e)), transform(filter(pii__all, x -> x.given <> ''), x -> struct(x.gkind as kind, lower(x.given) as normal, x.given as e)))"


def entity_table(docs: DataFrame) -> DataFrame:
    """kind, normal, e (one way of writing it): the distinct entities of all texts, names by their parts."""
    # explode_outer: for explode the optimiser would search every text once more, to drop empty lists early
    return _found(docs.select("text")).select(F.explode_outer(F.expr(_DRAWN)).alias("x")).filter("x is not null").groupBy("x.kind", "x.normal").agg(F.min("x.e").alias("e"))


_KINDS = [k for k in PATTERNS if k != "name"]


def _drawn(key: str) -> Column:
    """The replacement of the columns e, kind, normal, attempt. Kind by kind, as one long expression costs the parser much memory."""
    out = F.when(F.col("kind") == "name", F.expr(name_sql("e", "'name'", "normal", "attempt", key)))
    for k in _KINDS:
        out = out.when(F.col("kind") == k, F.expr(surrogate_sql("e", _q(k), "normal", "attempt", key)))
    return out.otherwise(F.expr(name_sql("e", "kind", "normal", "attempt", key)))


def redrawn(entities: DataFrame, key: str) -> DataFrame:
    """kind, normal, attempt of the entities whose first surrogates were not free, by rounds."""
    spark = entities.sparkSession
    # few bytes but much work a row: not to be merged into few tasks
    entities = entities.repartition(max(8, int(spark.conf.get("spark.sql.shuffle.partitions"))), "kind", "normal")
    draw, shape = _drawn(key), F.expr(_normal("s", "kind"))
    shaped = lambda df: df.withColumn("s", draw).withColumn("s", shape)
    now = written(shaped(entities.withColumn("attempt", F.lit(0))), "entities")
    originals = now.select("kind", F.col("normal").alias("s")).distinct()
    for _ in range(MAX_ROUNDS):
        clash = now.groupBy("kind", "s").agg(F.count(F.lit(1)).alias("n"), F.min("normal").alias("first")).filter("n > 1")
        again = now.join(clash, ["kind", "s"]).filter("normal <> first").select("kind", "normal")
        again = again.union(now.join(originals, ["kind", "s"], "left_semi").select("kind", "normal")).distinct()
        again = written(again, "clashes")
        if again.isEmpty():
            return now.filter("attempt > 0").select("kind", "normal", "attempt")
        marked = now.drop("s").join(again.withColumn("clash", F.lit(1)), ["kind", "normal"], "left")
        fresh = shaped(marked.filter("clash = 1").withColumn("attempt", F.col("attempt") + 1)).select("kind", "normal", "e", "attempt", "s")
        kept = now.join(again, ["kind", "normal"], "left_anti").select("kind", "normal", "e", "attempt", "s")
        now = written(kept.unionByName(fresh), "entities")
    raise RuntimeError(f"after {MAX_ROUNDS} rounds some kind still has more entities than surrogates: {[r.kind for r in again.select('kind').distinct().collect()]}")


@lru_cache
def _own_key() -> str:
    return secrets.token_hex(32)


def session_key(spark: SparkSession) -> str:
    """The key that the session's KEY_SETTING holds, else one that this program draws once."""
    return spark.conf.get(KEY_SETTING, None) or _own_key()


@lean_parser
def replace_entities(docs: DataFrame, key: str) -> DataFrame:
    """docs with every entity of text replaced, and n_entities; n_chars follows where present."""
    out_columns = [c for c in docs.columns if c != "n_entities"]
    moved = redrawn(entity_table(docs), key)
    rows = _found(docs)
    attempt = lambda kind, normal: "0"
    if not moved.isEmpty():
        # rows that hold a redrawn entity, each with its entities' attempts
        at_row = F.xxhash64(F.col("text"))
        held = rows.select(at_row.alias("pii__k"), F.explode_outer(F.expr(_DRAWN)).alias("x")).filter("x is not null").select("pii__k", "x.kind", "x.normal").distinct()
        lists = held.join(moved, ["kind", "normal"]).groupBy("pii__k").agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws("|", "kind", "normal"), "attempt"))).alias("pii__m"))
        lists = written(lists, "redrawn")
        if lists.count() <= BROADCAST_ROWS:
            lists = F.broadcast(lists)
        rows = rows.withColumn("pii__k", at_row).join(lists, "pii__k", "left")
        attempt = lambda kind, normal: f"coalesce(element_at(pii__m, concat({kind}, '|', {normal})), 0)"
    given = f"CASE WHEN x.given <> '' THEN concat({name_sql('x.given', 'x.gkind', 'lower(x.given)', attempt('x.gkind', 'lower(x.given)'), key)}, ' ') ELSE '' END"
    surname = name_sql("x.w", "'name'", "x.normal", attempt("'name'", "x.normal"), key)
    each = [F.expr(f"transform(pii__all, x -> CASE WHEN x.kind = 'name' THEN concat(x.title, {given}, {surname}) END)")]
    for k in _KINDS:
        # a secret keeps the words before its value
        drawn = surrogate_sql("x.w", _q(k), "x.normal", attempt(_q(k), "x.normal"), key)
        each.append(F.expr(f"transform(pii__all, x -> CASE WHEN x.kind = {_q(k)} THEN concat(substr(x.e, 1, length(x.e) - length(x.w)), {drawn}) END)"))
    new = reduce(lambda a, b: F.zip_with(a, b, lambda p, q: F.coalesce(p, q)), each)
    rows = rows.withColumn("pii__new", new).withColumn(
        "text", F.expr("CASE WHEN size(pii__all) > 0 THEN concat(array_join(zip_with(slice(pii__parts, 1, size(pii__new)), pii__new, (a, b) -> concat(a, b)), ''), element_at(pii__parts, -1)) ELSE text END")
    )
    if "n_chars" in docs.columns:
        rows = rows.withColumn("n_chars", F.length("text").cast(dict(docs.dtypes)["n_chars"]))
    return rows.select(*[F.col(f"`{c}`") for c in out_columns], F.size("pii__all").cast("long").alias("n_entities"))
