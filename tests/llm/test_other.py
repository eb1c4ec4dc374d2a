"""HTML extraction, decontamination, suffix dedup, pieces, near-duplicates, the pipeline."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

import corpus_pipeline
from hgpart.llm import components, decontamination, html_text, pieces, simhash, suffix_dedup
from tests.llm.cases import CLASHES, awkward, frame, natural, prose

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{{}}</style><script>var a="</p>"</script></head><body><header class="top">Site head</header>
<nav><ul><li><a href="/a">Menu</a></li></ul></nav><div class="cookie-notice">We use cookies</div><aside class="sidebar">Side</aside>{main}
<section id="comments"><p>Nice post!</p></section><form><label>Mail</label><input></form><footer>&copy; foot</footer></body></html>"""


def test_html_blocks():
    main = "<article><h1>Head &amp; line</h1><p><b>One\n  two<br><p>Th<i>re</i>e &lt;x&gt;</p><div class='ad'>Buy</div><ul><li>a<li>b</ul><!-- no --><table><tr><td>c</td><td>d</td></tr></table></article>"
    assert html_text.main_text(PAGE.format(main=main)) == "Head & line One two Three <x> a b c d"
    assert html_text.main_text("") == "" and html_text.main_text("plain &nbsp; words") == "plain words"
    assert html_text.main_text("<article><p>open") == "open"


def test_html_attributes_are_told_apart():
    for attrs in ('style="overflow:hidden"', 'title="hidden places"', 'data-id="comment"', "data-class='ad'", "title='a role=menu'", 'aria-hidden="false"', 'lang = "en" data-x=hidden'):
        assert html_text.main_text(f"<article {attrs}><div {attrs}>Kept</div></article>") == "Kept", attrs
    for attrs in ("hidden", 'style="a" hidden', 'aria-hidden="true"', "class=ad", "x='1'id='comment'", 'ROLE = "menu"', 'data-n="1" class="big ad"'):
        assert html_text.main_text(f"<article>Kept<div {attrs}>Gone</div></article>") == "Kept", attrs


def test_html_templates(spark):
    """Pages without an article tag: the slot and the fixed texts come from the host's template."""
    rows = [
        (k, f"https://h.example.com/{k}", f"<html><body><div class='box'><div class='bar'>Welcome to the shop</div><div class='item'>{prose(k, 60)}</div><div class='low'>Call us today</div></div></body></html>") for k in range(8)
    ]
    rows += [(20, None, None), (21, "not a url", "<p>x</p>"), (22, "https://solo.example.com/", PAGE.format(main="<article><p>Solo</p></article>")), (22, "https://solo.example.com/", PAGE.format(main="<article><p>Solo</p></article>"))]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", __import__("pyspark").sql.functions.lit("x"))
    out = html_text.extract(df).collect()
    assert len(out) == len(rows)
    by = {r.page_id: r for r in out}
    for k in range(8):
        assert by[k].text == prose(k, 60) and by[k].template
    assert by[20].text == "" and by[21].text == "x" and by[22].text == "Solo" and not by[22].template
    assert all(r.n_chars == len(r.text) for r in out)
    assert html_text.extract(df.limit(0)).count() == 0


def _extracted(spark, pages, host="https://h.example.com/"):
    df = spark.createDataFrame([(k, host and f"{host}{k}", h) for k, h in enumerate(pages)], "page_id long, url string, html string")
    return {r.page_id: r.text for r in html_text.extract(df).collect()}


def test_html_template_decides_over_article(spark):
    """The main text lies in a plain element, in sections of their own, and an article tag marks only a teaser."""
    def page(k):
        return f"<html><body><div class='low'><article><p>Teaser {k}</p></article></div><div class='box'><h1>Title {k}</h1><section><p>{prose(k, 60)}</p></section><section><p>{prose(k + 50, 60)}</p></section></div></body></html>"

    out = _extracted(spark, [page(k) for k in range(8)])
    assert out == {k: f"Title {k} {prose(k, 60)} {prose(k + 50, 60)}" for k in range(8)}
    out = _extracted(spark, [page(k) for k in range(3)])
    assert out == {k: f"Teaser {k}" for k in range(3)}  # no template: too few pages


@pytest.mark.parametrize("host", ["https://h.example.com/", None])
def test_html_copies_keep_their_text(spark, host):
    """Copies of one page, alike or but for a detail, are no template."""
    page = "<html><body><div class='box'><article><h1>Same</h1><p>One short text</p><ul><li>and more</li></ul></article><div class='low'>{}</div></div></body></html>"
    assert _extracted(spark, [page.format("x")] * 7, host) == {k: "Same One short text and more" for k in range(7)}
    out = _extracted(spark, [page.format(f"Page {k}") for k in range(7)], host)
    assert all(t.startswith("Same One short text and more") for t in out.values())
    out = _extracted(spark, [page.format(f"<p>Page {k}</p>") for k in range(7)], host)
    assert all(t.startswith("Same One short text and more") for t in out.values())
    inner = [page.format("x").replace("</ul>", f"</ul><p class='at'>{k}</p>") for k in range(7)]
    assert _extracted(spark, inner, host) == {k: f"Same One short text and more {k}" for k in range(7)}


def brute_main_texts(rows):
    """The main texts by occurrence vectors held as tuples and texts compared as such, without hashes or joins."""
    hosts = {}
    for _, url, page in rows:
        if page and (m := re.match(r"[a-z][a-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", (url or "").lower())):
            hosts.setdefault(m[1], {})[page] = None
    found = {}
    for host, pages in hosts.items():
        parsed, held, mass = [html_text.blocks(p) for p in pages], {}, Counter()
        if len(parsed) < 5:
            continue
        for k, (texts, tags) in enumerate(parsed):
            for token, n in [((t, None), n) for t, n in tags.items()] + list(Counter((p, t) for p, t, *_ in texts).items()):
                held.setdefault(token, [0] * len(parsed))[k] = n
            for path, text, linked, _, dropped in texts:
                weight = 0 if dropped else max(0, len(text) - 2 * linked)
                mass[path, text] += weight
                for up in tags:
                    mass[up, None] += weight * path.startswith(up + "/")
        classes = {}
        for token, vector in held.items():
            if sum(map(bool, vector)) >= 0.9 * len(parsed):
                classes.setdefault(tuple(vector), []).append(token)
        frames = {v: [p for p, t in c if t is None] for v, c in classes.items()}
        frames = {v: f for v, f in frames.items() if len(f) >= (2 if max(v) == 1 else 1)}
        valid = []
        for v, f in frames.items():
            slots = set()
            for p in f:
                if not any(p.startswith(q + "/") for q in f):
                    slots.add(max((q for w, g in frames.items() if w != v for q in g if p.startswith(q + "/")), key=len, default=""))
            if len(slots) == 1:
                valid.append(v)
        fixed = {(p, t) for v in valid for p, t in classes[v] if t is not None}
        total, same = sum(m for (_, t), m in mass.items() if t is not None), sum(mass[x] for x in fixed)
        frame = [p for v in valid if max(v) == 1 for p in frames[v]]
        if not frame or total < 2 * same:
            continue
        inner = {p: mass[p, None] - sum(mass[x] for x in fixed if x[0].startswith(p + "/")) for p in frame}
        full = [p for p in frame if inner[p] > 0 and inner[p] >= 0.9 * (total - same)]
        found[host] = (max(full, key=lambda p: (len(p), p), default=None), fixed)
    out = []
    for _, url, page in rows:
        m = re.match(r"[a-z][a-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", (url or "").lower())
        content, fixed = found.get(m and m[1], (None, set()))
        texts = [b for b in html_text.blocks(page or "")[0] if not b[4]]
        texts = [b for b in texts if content and (b[0] + "/").startswith(content + "/")] or [b for b in texts if b[3]] or texts
        out.append(" ".join(t for p, t, *_ in texts if (p, t) not in fixed or re.match(r"h[1-6](\.|$)", p.rpartition("/")[2])))
    return out


def test_html_against_brute_force(spark):
    pages = [tuple(r) for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").select("page_id", "url", "html").collect()]
    shop = "<body><div class=top>Shop of {}</div><ul>{}</ul><div class=box>{}</div><p class=low>{}</p></body>"
    items = lambda k: "".join(f"<li><b>{prose(k + j, 3)}</b><p class=more>Read on</p></li>" for j in range(1 + k % 4))
    pages += [(1000 + k, f"https://shop.example.org/{k}", shop.format("all things", items(k), prose(k, 150), "Long notice " * 20)) for k in range(9)]
    pages += [(1000, "https://shop.example.org/0", pages[-9][2]), (None, None, None), (2000, "odd", pages[-1][2]), (2001, "http://x.org", "")]
    got = html_text.extract(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()
    want = brute_main_texts(pages)
    assert Counter((r.page_id, r.text) for r in got) == Counter((p, t) for (p, *_), t in zip(pages, want))
    by = {r.page_id: r.text for r in got}
    assert all("Read on" not in by[1000 + k] and "notice" not in by[1000 + k] and prose(k, 150) in by[1000 + k] for k in range(9)) and "notice" in by[2000]


def test_html_classes_nest():
    assert html_text.nest([["/b", "/b/d"], ["/b/d/li", "/b/d/li/p"], ["/b/x", "/b/d/y"], ["/b/d/li/p/i"]]) == ["", "/b/d", None, "/b/d/li/p"]


def test_html_shared_headings_stay(spark):
    out = _extracted(spark, [f"<html><body><div class='all'><article><h1>News</h1><div class='bar'>Read it to friends</div><p>{prose(k, 60)}</p></article></div></body></html>" for k in range(8)])
    assert out == {k: f"News {prose(k, 60)}" for k in range(8)}


def test_cgk_distance():
    r = random.Random(3)
    for _ in range(200):
        item, text = [r.randrange(6) for _ in range(r.randrange(1, 12))], [r.randrange(6) for _ in range(r.randrange(0, 30))]
        best = min(edit(item, text[a:b]) for a in range(len(text) + 1) for b in range(a, len(text) + 1))
        assert decontamination.best_distance(item, text)[0] == best


def edit(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_decontamination(spark):
    r = random.Random(5)
    items = [(k, " ".join(f"w{r.randrange(400)}" for _ in range(12 + 3 * k))) for k in range(20)] + [(90, None), (91, ""), (92, "--"), (None, "lonely item of nobody with seven words")]
    docs, truth = [], set()
    for k, (item, text) in enumerate(items[:20]):
        words = text.split()
        for e in range(int(0.2 * len(words)) + 1):
            w = list(words)
            for _ in range(e):
                at = r.randrange(len(w))
                w[at : at + 1] = r.choice(([], ["zz"], [w[at], "yy"]))
            d = 1000 + 50 * k + e
            docs.append((d, f"{prose(d, 40)}\n{' '.join(w).upper()}!\n{prose(d + 1, 40)}", "en", "s", 1))
            truth.add((d, item))
    docs += awkward()
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(x.doc_id, x.item_id) for x in decontamination.contaminated(frame(spark, docs, extra=CLASHES), bench).collect()}
    assert got <= truth and len(got) >= 0.9 * len(truth)
    exact = {(d, i) for d, i in truth if (d - 1000) % 50 == 0}
    assert exact <= got
    kept = decontamination.drop_contaminated(frame(spark, docs), bench)
    assert Counter(x.doc_id for x in kept.collect()) == Counter(d for d, *_ in docs if d not in {a for a, _ in got})
    assert decontamination.contaminated(frame(spark, []), bench).count() == 0
    assert decontamination.contaminated(frame(spark), bench.limit(0)).count() == 0
    blocked = decontamination.contaminated(frame(spark, docs), bench, block_bytes=1500)
    assert {(x.doc_id, x.item_id) for x in blocked.collect()} == got


def test_decontamination_of_long_items():
    """Items of 300 to 900 words with up to a fifth of their words edited: at least 0.9 of them are found, all unedited ones too."""
    r = random.Random(9)
    items = [(k, " ".join(f"w{r.randrange(3000)}" for _ in range(300 + 60 * k))) for k in range(11)]
    index, found, tried = decontamination.Index(items), 0, 0
    for share in (0, 0.05, 0.1, 0.15, 0.19):
        texts = []
        for _, t in items:
            w = t.split()
            for _ in range(int(share * len(w))):
                at = r.randrange(len(w))
                w[at : at + 1] = r.choice(([], ["zz"], [w[at], "yy"]))
            texts.append(f"{prose(1, 100)} {' '.join(w)} {prose(2, 100)}".encode())
        hits = {(t, i) for t, i, *_ in index.matches(decontamination.Words(texts))}
        assert all(t == i for t, i in hits) and (share or len(hits) == len(items))
        found, tried = found + len(hits), tried + len(items)
    assert found >= 0.9 * tried


def test_decontamination_in_small_parts(monkeypatch):
    """A gram that many items share, at many places of a text, taken a few pairs at a time."""
    items = [(k, f"how to do the thing number n{k} and all of the thing number") for k in range(30)]
    texts = [" ".join(t for _, t in items[k : k + 9]).encode() for k in range(5)] + [b"the thing number " * 40]
    index = decontamination.Index(items)
    whole = sorted(index.matches(decontamination.Words(texts)))
    monkeypatch.setattr(decontamination, "MET_AT_ONCE", 50)
    assert sorted(index.matches(decontamination.Words(texts))) == whole and len(whole) >= 45


def brute_repeats(texts, span=suffix_dedup.SPAN):
    raw = [(t or "").encode() for t in texts]
    count = Counter(r[i : i + span] for r in raw for i in range(len(r) - span + 1))
    out = []
    for r in raw:
        hit = np.zeros(len(r) + 1, np.int64)
        for i in range(len(r) - span + 1):
            if count[r[i : i + span]] > 1:
                hit[i : i + span] = 1
        spans = int((np.diff(np.concatenate([[0], hit])) == 1).sum())
        left = bytes(b for b, h in zip(r, hit) if not h)
        out.append((len(r), len(r) - len(left), spans, hashlib.sha256(left).hexdigest()))
    return out


@pytest.mark.parametrize("crowd, segment", [(256, 1 << 20), (1, 1 << 20), (256, 3000)])
def test_suffix_dedup(spark, monkeypatch, crowd, segment):
    monkeypatch.setattr(suffix_dedup, "CROWD", crowd)
    monkeypatch.setattr(suffix_dedup, "SEGMENT", segment)
    shared = prose(7, 70)
    rows = awkward() + [(200 + k, f"{prose(300 + k, 20)} {shared} {prose(400 + k, 25)}", "en", "s", 1) for k in range(12)] + [(300, "ab" * 500, "en", "s", 1), (301, "x" * 199, "en", "s", 1), (302, "x" * 199, "en", "s", 1)]
    got = Counter(tuple(r) for r in suffix_dedup.repeat_report(frame(spark, rows, extra=CLASHES)).collect())
    assert got == Counter((d, *e) for (d, *_), e in zip(rows, brute_repeats([t for _, t, *_ in rows])))
    assert suffix_dedup.repeat_report(frame(spark, [])).count() == 0


def test_suffix_dedup_meets_the_grams_share_by_share(spark, monkeypatch):
    """No written table of shared blocks, so no shuffle behind one, holds grams of two shares; together they hold all."""
    tables = []
    written = lambda df, label: tables.append((label, out := suffix_dedup_written(df, label))) or out
    suffix_dedup_written = suffix_dedup.written
    monkeypatch.setattr(suffix_dedup, "written", written)
    rows = [(k, f"{prose(20 + k % 5, 250)} {prose(800 + k, 30)}", "en", "s", 1) for k in range(15)]
    got = Counter(tuple(r) for r in suffix_dedup.repeat_report(frame(spark, rows)).collect())
    assert got == Counter((d, *e) for (d, *_), e in zip(rows, brute_repeats([t for _, t, *_ in rows])))
    held = [{r.g % suffix_dedup.SHARES for r in df.select("g").collect()} for label, df in tables if label == "shared"]
    assert held == [{k} for k in range(suffix_dedup.SHARES)] and suffix_dedup.SHARES > 1


def test_suffix_dedup_packs_the_windows_of_a_crowd():
    """No row for each window: crowded blocks make a row for each bucket, with all of their windows."""
    import numpy as np
    import pyarrow as pa

    rng, span, width = np.random.default_rng(3), suffix_dedup.SPAN, 350
    texts = [bytes(rng.integers(97, 123, width, dtype=np.uint8)) for _ in range(40)]
    texts[1] = texts[0][:250] + texts[1][250:]
    place = int(suffix_dedup._packed(np.array([0]), np.array([width]), np.array([7]))[0])
    names = ["rk", "did", "raw", "a_place", "a_g", "a_w", "a_x"]
    batch = pa.RecordBatch.from_arrays([pa.array(range(40)), pa.array(range(40)), pa.array(texts), *(pa.array([[x]] * 40) for x in (place, 5, 1, True))], names)
    out = pa.Table.from_batches(suffix_dedup._edge_blocks(4)([batch]))
    packed = out.filter(pa.compute.is_valid(out.column("h")))
    assert len(packed) == 4 and len(out) == 8
    assert sum(map(len, packed.column("raw").to_pylist())) == 48 * (40 * (width - span + 1) - 51)
    twice = packed.select(["h", "raw"]).sort_by("h").to_batches()
    assert sum(len(x) for x in suffix_dedup._met_windows(twice)) == 0  # what they share is known already
    again = pa.concat_tables([packed, packed]).select(["h", "raw"]).sort_by("h").combine_chunks().to_batches()
    assert sum(len(x) for x in suffix_dedup._met_windows(again)) == 2 * (40 * (width - span + 1) - 2 * 51)


def test_suffix_dedup_of_a_crowd_at_the_real_limits(spark):
    """More than CROWD different blocks of one k-gram, some of whose windows agree; none of them repeats in whole."""
    core = prose(11, 40)[:120]
    sides = [prose(700 + k, 14) for k in range(3)]
    rows = [(k, f"{prose(1000 + k, 9)} {sides[k % 3] if k % 4 == 0 else prose(5000 + k, 14)} {core} {prose(9000 + k, 30)}", "en", "s", 1) for k in range(suffix_dedup.CROWD + 60)]
    got = Counter(tuple(r) for r in suffix_dedup.repeat_report(frame(spark, rows)).collect())
    assert got == Counter((d, *e) for (d, *_), e in zip(rows, brute_repeats([t for _, t, *_ in rows])))
    assert sum(r[2] > 0 for r in got) > 40


def test_blocks_of_long_texts_keep_their_place(monkeypatch):
    monkeypatch.setattr(suffix_dedup, "SEGMENT", 3000)
    texts = [prose(k, 900).encode() for k in range(3)] + [b"=-" * 4000]
    batch = pa.RecordBatch.from_arrays([pa.array(range(4)), pa.array(range(4)), pa.array(texts, pa.binary())], ["rk", "did", "raw"])
    windows = [set() for _ in texts]
    for out in suffix_dedup._anchors([batch]):
        for g, b, c, n, place, rk, _ in zip(*(x.to_pylist() for x in out.columns)):
            at, size, shift = (b, c - b, 0) if g is None else suffix_dedup._unpacked(place)
            windows[rk].update(range(at, at + size - suffix_dedup.SPAN + 1))
            assert g is None or shift + suffix_dedup.GRAM <= suffix_dedup.SPAN
    assert [w == set(range(len(t) - suffix_dedup.SPAN + 1)) for w, t in zip(windows, texts)] == [True] * 4


@settings(max_examples=60, deadline=None)
@given(st.lists(st.binary(min_size=1, max_size=40), min_size=1, max_size=6), st.integers(1, 12))
def test_suffix_order(parts, most):
    raw = np.frombuffer(b"".join(parts) + b"\0" * most, np.uint8)
    starts = np.arange(len(raw) - most + 1)
    classes = starts % 3
    order = suffix_dedup.sort_suffixes(raw, starts, classes, most)
    keys = [(classes[i], bytes(raw[starts[i] : starts[i] + most])) for i in order]
    assert keys == sorted(keys) and sorted(order.tolist()) == list(range(len(starts)))
    count = Counter(keys)
    flags = suffix_dedup.equal_neighbours(raw, starts, classes, most)
    assert all(flags[i] == (count[classes[i], bytes(raw[starts[i] : starts[i] + most])] > 1) for i in range(len(starts)))


ODD = ["", "a  b", "   ", "x   y     z", " lead", "trail ", "日本語 テスト  漢字", "emoji 😀  😀 ok", "tab\there\n\nnew\r\n", "  \n  x", "a" * 300, " " * 40 + "x", "αβγ  δ", "  日", "a\0b", "İstanbul ﬁ ñ"]


def test_pieces_match_the_library(spark):
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=pieces.DEFAULT_MODEL)
    texts = ODD + [t or "" for _, t, *_ in awkward()] + ["▁weird ▁▁x"]
    ids = pieces.codec().encode(texts)
    for t, i in zip(texts, ids):
        assert np.frombuffer(i, np.int32).tolist() == library.encode(t)
    assert all(pieces.codec().decode(i) == t for t, i in zip(texts[:-1], ids))
    rows = {r.doc_id: r for r in pieces.token_digests(frame(spark, [(k, t, "en", "s", 1) for k, t in enumerate(ODD)] + [(None, None, None, None, None)], extra=CLASHES)).collect()}
    assert all(rows[k].n_tokens == len(library.encode(t)) and rows[k].round_trip for k, t in enumerate(ODD)) and rows[None].n_tokens == 0
    df = frame(spark, [(k, t, "en", "s", 1) for k, t in enumerate(ODD)])
    assert {r.doc_id: r.text for r in pieces.decoded(pieces.encoded(df)).collect()} == dict(enumerate(ODD))
    assert pieces.token_digests(frame(spark, [])).count() == 0


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(alphabet="aehinorst ▁.,é\n", max_size=30), max_size=5))
def test_pieces_on_random_text(texts):
    import sentencepiece

    if not hasattr(test_pieces_on_random_text, "library"):
        test_pieces_on_random_text.library = sentencepiece.SentencePieceProcessor(model_file=pieces.DEFAULT_MODEL)
    for t, i in zip(texts, pieces.codec().encode(texts)):
        assert np.frombuffer(i, np.int32).tolist() == test_pieces_on_random_text.library.encode(t)


def brute_fingerprint(text):
    w = re.findall(b"[^\x20\x09-\x0d]+", (text or "").encode().lower())
    h = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 4]), 42) for i in range(max(1, len(w) - 3))] if w else []
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def test_fingerprints():
    for _, t, *_ in awkward():
        assert simhash.fingerprint(t) == brute_fingerprint(t)


def test_anchors_cover_every_close_pair():
    r = np.random.default_rng(1)
    low, high, leader = simhash.code_tables()
    assert (leader >= 0).all()  # the code is perfect
    a = r.integers(0, 1 << 63, 3000, dtype=np.uint64) * np.uint64(2) + r.integers(0, 2, 3000, dtype=np.uint64)
    b = a.copy()
    for k in range(4):
        b ^= np.uint64(1) << r.integers(0, 64, len(b)).astype(np.uint64)
    home = np.stack(simhash.homes(a.view(np.int64)), axis=1)
    row, key = simhash.replicas(b.view(np.int64))
    met = np.zeros(len(a), bool)
    np.logical_or.at(met, row, (home[row] == key[:, None]).any(axis=1))
    assert met.all()


def test_near_duplicates(spark):
    rows = awkward() + [(400 + k, prose(9, 400) + f" end{k}", "en", "s", 1) for k in range(6)]
    got = simhash.near_duplicate_groups(frame(spark, rows, extra=CLASHES)).collect()
    fp = [brute_fingerprint(t) for _, t, *_ in rows]
    root = list(range(len(rows)))
    changed = True
    while changed:
        changed = False
        for i in range(len(rows)):
            for j in range(len(rows)):
                if (fp[i] ^ fp[j]).bit_count() <= 4 and root[i] != root[j]:
                    root[i] = root[j] = min(root[i], root[j])
                    changed = True
    groups = {}
    for i, (d, *_) in enumerate(rows):
        groups.setdefault(root[i], []).append(d)
    least = {k: min((d for d in v if d is not None), default=None) for k, v in groups.items()}
    assert Counter(tuple(r) for r in got) == Counter((d, f"{fp[i]:016x}", least[root[i]]) for i, (d, *_) in enumerate(rows))
    assert simhash.near_duplicate_groups(frame(spark, [])).count() == 0
    kept = Counter(r.doc_id for r in simhash.keep_one_per_group(frame(spark, rows)).collect())
    assert set(kept) == {v for v in least.values()} | {None} and all(n == 1 for d, n in kept.items() if d is not None)


@pytest.mark.parametrize("one_task", [components.ONE_TASK, 0])
def test_components_on_chains(spark, monkeypatch, one_task):
    monkeypatch.setattr(components, "ONE_TASK", one_task)
    r = random.Random(2)
    nodes = list(range(60))
    r.shuffle(nodes)
    edges = [(nodes[k], nodes[k + 1]) for k in range(39)] + [(nodes[45], nodes[50]), (nodes[50], nodes[45]), (7, 7)]
    got = {x.node: x.root for x in components.smallest_reachable(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[n] == min(nodes[:40]) for n in nodes[:40]) and got[nodes[45]] == got[nodes[50]] == min(nodes[45], nodes[50])


def test_a_dense_group_leaves_a_task_as_a_forest(spark):
    edges = [(a, b) for a in range(120) for b in range(a)] + [(200, 201), (201, 200)]
    left = components.spanning_forest(spark.createDataFrame(edges, "a long, b long").coalesce(1)).collect()
    assert len(left) == 119 + 1 and {tuple(x) for x in left} <= set(edges)


def test_pipeline(spark, tmp_path):
    leak = " ".join(f"q{k}" for k in range(30))
    good = [(60 + k, natural(800 + k, 200), "en", "s", 1) for k in range(6)]
    rows = awkward() + good + [(70, good[0][1], "en", "s", 1), (71, f"{natural(3000, 200)} {leak}", "en", "s", 1), (72, f"{natural(3001, 200)} mail bob.jones@mail.example.com", "en", "s", 1)]
    frame(spark, rows, extra=("extra",)).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, leak)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, seen = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        before = docs.columns
        docs = stage(spark, docs, str(tmp_path)).cache()
        seen[name] = docs.collect()
        if name != "piece ids":
            assert docs.columns == before
    ids = {k: {r.doc_id for r in v} for k, v in seen.items()}
    assert {1, 2, 3, 8}.isdisjoint(ids["quality rules"]) and {60, 70, 71, 72} <= ids["quality rules"]
    assert 60 in ids["SimHash near-duplicates"] and 70 not in ids["SimHash near-duplicates"]
    assert 71 in ids["SimHash near-duplicates"] and 71 not in ids["benchmark decontamination"]
    text = next(r.text for r in seen["surrogates"] if r.doc_id == 72)
    assert "bob.jones" not in text and "@" in text
    assert Counter(tuple(r) for r in corpus_pipeline.run(spark, str(tmp_path)).collect()) == Counter(tuple(r) for r in seen["piece ids"])
    assert all(r.round_trip for r in seen["piece ids"])
