"""Small tables with awkward rows."""

import random

LOREM = "the river of stones and light in a valley that is wide to every traveller for it was old".split()


def prose(seed: int, n: int) -> str:
    r = random.Random(seed)
    return " ".join(r.choice(LOREM) + ("" if r.random() < 0.5 else str(r.randrange(40))) for _ in range(n))


def natural(seed: int, n: int) -> str:
    """Prose with the usual shares of common words, capitals and stops."""
    r, out = random.Random(seed), []
    common = ["the", "of", "and", "to", "a", "in", "is", "that", "it", "for"]
    shares = [0.0616, 0.036, 0.0255, 0.02, 0.0162, 0.0138, 0.012, 0.0104, 0.0093, 0.0084]
    start = True
    for _ in range(n):
        w = r.choices(common, shares)[0] if r.random() < sum(shares) else "".join(r.choice("etaoinshrdlu") for _ in range(r.randrange(3, 9)))
        out.append((w.capitalize() if start else w) + (stop := "." if r.random() < 0.12 else ""))
        start = bool(stop)
    return " ".join(out)


def awkward():
    """(doc_id, text, lang, source, n_chars) with nulls, empties, copies, repeats, one long text, odd characters."""
    long = prose(1, 9000)
    rows = [
        (1, None, "en", "s", None), (2, "", "en", None, 0), (3, " \t\n ", None, "s", 4), (None, prose(2, 80), "en", "s", 1), (4, prose(3, 120), "en", "s", 1),
        (5, prose(3, 120), "de", "s", 1), (5, prose(3, 120), "de", "s", 1), (6, long, "xx", "s", 1), (7, long + " tail", "en", "s", 1), (8, "one two three", "en", "s", 1),
        (9, "É ñ 漢字 😀 \x0b\x0c x" * 30, "fr", "s", 1), (10, "a" * 700, "en", "s", 1), (11, "\n".join(["same line here"] * 40), "en", "s", 1),
    ]
    return rows + [(100 + k, prose(50 + k // 2, 60 + k), "en", "s", 1) for k in range(20)]


SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, rows=None, extra=()):
    df = spark.createDataFrame(awkward() if rows is None else rows, SCHEMA)
    from pyspark.sql import functions as F

    for name in extra:
        df = df.withColumn(name, F.lit("x"))
    return df


CLASHES = ("shard", "slot", "fp", "root", "n_words", "kept", "rk", "did", "g", "b", "n_entities", "component_id", "raw", "item_id", "license", "n_tokens")
