"""Main text of web pages by equivalence-class template deduction.

Tokens are start tags, told apart by their path, and blocks of text. Over the pages of a host each token has an
occurrence vector: how often each page holds it. Tokens with equal vectors form an equivalence class; the vectors are
compared by an order-free hash, so no task holds a host's pages. A class is valid if it occurs in (nearly) all
pages of a host with enough of them, and all its elements lie in one slot of the class around it. Valid classes nest
into the host's template: a class stands in the one that owns the deepest element around all of its own (nest); classes
that pages hold once are the frame, those they hold more often are repeated items. Text tokens of a valid class are
template text; what lies between the tags of the tree are slots. The content is the deepest element of the frame
that holds (nearly) all unlinked text in its inner elements, menus and the like and template texts apart; its slots are
the main text. Hosts without a template, and pages without their host's content element, are read by their article tags.

Copies of a page count once, and hosts most of whose text is the same on all pages have no template. Template texts
are dropped within the content too, but never its headings.

Edge cases: null html gives an empty text; pages with a null or odd url have no host, and are read by their tags
alone, as are hosts with few different pages; repeated rows are returned each, an empty table gives an empty result,
further columns are ignored.
"""

from __future__ import annotations

import hashlib
import html as entities
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgpart.llm.tables import written

MIN_PAGES = 5
SUPPORT = 0.9
#: Copies of each host's template, so that the pages of a large host are joined in many tasks.
SALT = 32
#: Templates of this many characters in all are sent to every task; more are joined by salted host.
BROADCAST_CHARS = 16 << 20
#: Kinds of tokens.
TAG, TEXT = 0, 1

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?\]\]>|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
_RAW_END = {t: re.compile(rf"</{t}\s*>", re.I) for t in ("script", "style", "textarea", "title", "noscript", "template", "iframe", "svg", "select", "option")}
_RAW = {"script", "style", "template", "iframe", "svg", "textarea", "select", "noscript"}
_ATTR = re.compile(r"([^\s=>/]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+)))?")
_HEADING = re.compile(r"h[1-6](?:\.|$)")
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
_BLOCK = set("address article aside blockquote body br center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
_CLOSES_P = _BLOCK - {"br", "body", "html"}
_DROP = {"nav", "footer", "aside", "form", "button", "head", "title", "menu", "dialog", *_RAW}
_DROP_ROLES = {"navigation", "banner", "complementary", "contentinfo", "search", "menu", "menubar", "dialog", "alert", "form"}
#: Parts of class and id names that mark what is not main text.
_DROP_NAMES = set(
    "ad ads advert adverts advertisement advertising adbox adsense sponsor sponsored promo promotion banner sidebar sidebars nav navbar navigation menu menus topmenu breadcrumb breadcrumbs footer footers "
    "comment comments commentlist respond reply replies disqus notice notices cookie cookies consent gdpr alert popup modal overlay newsletter subscribe subscription signup login share sharing social related recommended "
    "recommendations widget widgets toolbar pagination pager skip masthead disclaimer copyright".split()
)
_HEADER_NAMES = {"header", "headers", "topbar"}
_CONTENT_NAMES = {"article", "post", "entry", "content", "story", "main", "body", "text"}


def _marks(attrs: str) -> tuple[set[str], str, bool, str]:
    """Parts of class and id, role, hidden or not, and class as written."""
    parts, role, hidden, label = set(), "", False, ""
    for m in _ATTR.finditer(attrs):
        name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if name in ("class", "id"):
            parts.update(re.split(r"[^a-z]+", value))
            label = label or value
        elif name == "role":
            role = value
        elif name == "hidden" or name == "aria-hidden" and value == "true":
            hidden = True
    return parts, role, hidden, label


def blocks(page: str):
    """Blocks of a page in order: (path, text, linked characters, in an article, dropped) and the paths of all start tags.

    An element is dropped with all that it holds if its tag, role or names say so."""
    out, tags = [], Counter()
    stack: list[tuple[str, str, bool, bool, bool]] = []  # tag, path, dropped, article, link
    text: list[str] = []
    linked = 0

    def flush():
        nonlocal text, linked
        joined = " ".join("".join(text).split()) if text else ""
        if joined:
            top = stack[-1] if stack else ("", "", False, False, False)
            out.append((top[1], joined, linked, top[3], top[2]))
        text, linked = [], 0

    def say(raw: str):
        nonlocal linked
        if raw:
            raw = entities.unescape(raw) if "&" in raw else raw
            text.append(raw)
            if stack and stack[-1][4]:
                linked += len(raw)

    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        if not m:
            say(page[at:])
            break
        say(page[at : m.start()])
        at = m.end()
        tag = (m[2] or "").lower()
        if not tag:
            if m[0].startswith("<![CDATA["):
                say(m[0][9:-3])
            continue
        if m[1]:
            if tag in _BLOCK:
                flush()
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    # a closing inline tag does not close blocks around it
                    if tag in _BLOCK or not any(s[0] in _BLOCK for s in stack[k + 1 :]):
                        if any(s[0] in _BLOCK for s in stack[k:]):
                            flush()
                        del stack[k:]
                    break
            continue
        if tag in _BLOCK:
            flush()
            if tag in _CLOSES_P:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] == "p":
                        del stack[k:]
                        break
                    if stack[k][0] in _BLOCK:
                        break
                if tag in ("li", "dd", "dt", "tr", "td", "th"):
                    for k in range(len(stack) - 1, -1, -1):
                        if stack[k][0] == tag:
                            del stack[k:]
                            break
                        if stack[k][0] in ("ul", "ol", "dl", "table", "div", "article"):
                            break
        parts, role, hidden, label = _marks(m[3]) if m[3] else (set(), "", False, "")
        up = stack[-1] if stack else ("", "", False, False, False)
        article = up[3] or tag in ("article", "main") or role in ("article", "main")
        named = bool(parts & _DROP_NAMES) or (bool(parts & _HEADER_NAMES) and not parts & _CONTENT_NAMES)
        dropped = up[2] or tag in _DROP or hidden or role in _DROP_ROLES or (named and tag not in ("html", "body", "article", "main")) or (tag == "header" and not article)
        path = up[1] + "/" + tag + (f".{label}" if label and tag in _BLOCK else "")
        if tag in _BLOCK:
            tags[path] += 1
        if tag in _VOID or m[3].endswith("/") and tag not in _BLOCK and tag not in _RAW:
            continue
        if tag in _RAW:
            end = _RAW_END[tag].search(page, at)
            at = end.end() if end else n
            continue
        stack.append((tag, path if tag in _BLOCK else up[1], dropped, article, up[4] or tag == "a"))
    flush()
    return out, tags


def _text_token(path: str, text: str) -> str:
    """Path and a 128-bit hash of the text."""
    return f"{path}#{hashlib.blake2b(text.encode('utf-8', 'surrogatepass'), digest_size=16).hexdigest()}"


def page_tokens(pages: DataFrame) -> DataFrame:
    """host, page (hash of its html), token, kind (TAG or TEXT), times, mass: what each page counts.

    The mass of a tag is the unlinked text kept in the elements inside it; the tag '' stands for the whole page."""

    def run(batches):
        for batch in batches:
            cols: list[list] = [[] for _ in range(6)]
            for key, host, page in zip(*(c.to_pylist() for c in batch.columns)):
                found, tags = blocks(page or "")
                texts, own, inner = {}, Counter(), Counter()
                for path, text, linked, _, dropped in found:
                    mass = 0 if dropped else max(0, len(text) - 2 * linked)
                    own[path] += mass
                    t = texts.setdefault(_text_token(path, text), [TEXT, 0, 0])
                    t[1] += 1
                    t[2] += mass
                for path, mass in own.items():
                    inner[""] += mass
                    while path := path.rpartition("/")[0]:
                        inner[path] += mass
                rows = [("", TAG, 1, inner[""]), *((t, TAG, times, inner[t]) for t, times in tags.items()), *((t, *x) for t, x in texts.items())]
                for row in rows:
                    for c, v in zip(cols, (host, key, *row)):
                        c.append(v)
            kinds = [pa.string(), pa.int64(), pa.string(), pa.int32(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], ["host", "page", "token", "kind", "times", "mass"])

    return pages.mapInArrow(run, "host string, page long, token string, kind int, times long, mass long")


def with_host(pages: DataFrame) -> DataFrame:
    """page_id, host (null for a null or odd url), html, url."""
    host = F.nullif(F.regexp_extract(F.lower(F.coalesce("url", F.lit(""))), r"^[a-z][a-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", 1), F.lit(""))
    return pages.select(F.col("page_id").cast("long"), host.alias("host"), F.col("html").cast("string").alias("html"), F.col("url").cast("string").alias("url"))


def _around(path: str, owners: dict[str, int], but: int) -> str:
    """The deepest element around path that another class owns; '' is the page."""
    while path:
        path = path.rpartition("/")[0]
        if owners.get(path, but) != but:
            break
    return path


def nest(classes: list[list[str]]) -> list[str | None]:
    """For each class, given as the paths of its tags, the element in which all of it lies: a path that another class owns, or ''
    for the page; None for a class that is not valid, as its elements lie in several slots."""
    owners = {path: k for k, paths in enumerate(classes) for path in paths}
    out: list[str | None] = []
    for k, paths in enumerate(classes):
        # a class that frames others has inner elements of its own; its outermost ones decide
        outermost = [p for p in paths if not any(p.startswith(q + "/") for q in paths)]
        slots = {_around(p, owners, k) for p in outermost}
        out.append(slots.pop() if len(slots) == 1 else None)
    return out


def deduce(classes: list[dict], support: float = SUPPORT) -> tuple[str | None, list[str]] | None:
    """The content element and the template texts of a host, from its classes: most (times in a page), tags and texts (token and
    mass of each); None if they make no template."""
    total = sum(x["mass"] for c in classes for x in c["tags"] if not x["token"])
    classes = [{**c, "tags": [x for x in c["tags"] if x["token"]]} for c in classes]
    classes = [c for c in classes if len(c["tags"]) >= (2 if c["most"] == 1 else 1)]
    slots = nest([[x["token"] for x in c["tags"]] for c in classes])
    valid = [c for c, slot in zip(classes, slots) if slot is not None]
    frame = [x for c in valid if c["most"] == 1 for x in c["tags"]]
    if not frame:
        return None
    texts = [x for c in valid for x in c["texts"]]
    fixed = sum(x["mass"] for x in texts)
    # where most text is the same on all pages, they are copies but for details, and give no template
    if total < 2 * fixed:
        return None
    content = None
    for x in frame:
        inner = x["mass"] - sum(t["mass"] for t in texts if t["token"].startswith(x["token"] + "/"))
        # of elements that each hold nearly all, one lies in the other, and the longest path is the deepest
        if inner > 0 and inner >= support * (total - fixed) and (content is None or (len(x["token"]), x["token"]) > (len(content), content)):
            content = x["token"]
    return content, [x["token"] for x in texts]


def _deduced(support: float):
    def run(batches):
        for batch in batches:
            hosts, found = batch.column(0).to_pylist(), [deduce(c, support) for c in batch.column(1).to_pylist()]
            kept = [(h, *f) for h, f in zip(hosts, found) if f]
            columns = list(zip(*kept)) or [[]] * 3
            kinds = [pa.string(), pa.string(), pa.list_(pa.string())]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], ["host", "content", "boilerplate"])

    return run


def templates(pages: DataFrame, min_pages: int = MIN_PAGES, support: float = SUPPORT) -> DataFrame:
    """host, content (path of the content element), boilerplate (template texts): one row for each host with a template.

    A task gets the tokens of a host that (nearly) all of its pages hold, which a page bounds."""
    keyed = pages.filter("host is not null").select(F.xxhash64("html").alias("page"), "host", "html")
    size = keyed.groupBy("host").agg(F.count_distinct("page").alias("pages")).filter(F.col("pages") >= min_pages)
    # copies of a page count once
    tokens = page_tokens(keyed).groupBy("host", "page", "token", "kind").agg(F.max("times").alias("times"), F.max("mass").alias("mass"))
    counted = tokens.groupBy("host", "token", "kind").agg(
        F.count(F.lit(1)).alias("n"),
        F.max("times").alias("most"),
        F.bit_xor(F.xxhash64("page", "times")).alias("vector"),
        F.sum("mass").alias("mass"),
    ).filter(F.col("n") >= min_pages * support)
    frequent = counted.join(size, "host").filter(F.col("n") >= F.col("pages") * support)
    item = F.struct("token", "mass")
    classes = frequent.groupBy("host", "vector").agg(
        F.max("most").alias("most"), F.collect_list(F.when(F.col("kind") == TAG, item)).alias("tags"), F.collect_list(F.when(F.col("kind") == TEXT, item)).alias("texts")
    )
    hosts = classes.groupBy("host").agg(F.collect_list(F.struct("most", "tags", "texts")).alias("classes"))
    return hosts.mapInArrow(_deduced(support), "host string, content string, boilerplate array<string>")


def _is_template(path: str, text: str, boilerplate: frozenset[str]) -> bool:
    """Headings of the content stay, though all pages share them."""
    return _text_token(path, text) in boilerplate and not _HEADING.match(path.rpartition("/")[2])


def main_text(page: str, content: str | None = None, boilerplate: frozenset[str] = frozenset()) -> str:
    found = [b for b in blocks(page)[0] if not b[4]]
    inside = [b for b in found if content and (b[0] == content or b[0].startswith(content + "/"))]
    kept = inside or [b for b in found if b[3]] or found
    return " ".join(text for path, text, *_ in kept if not (boilerplate and _is_template(path, text, boilerplate)))


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars, template (whether its host's template was deduced), for every row."""
    given = with_host(pages)
    frames = written(templates(given), "templates")
    size = frames.agg(F.sum(F.length("host") + F.length(F.coalesce("content", F.lit(""))) + F.length(F.array_join("boilerplate", " ")) + 64)).first()[0] or 0
    if size <= BROADCAST_CHARS:
        joined = given.join(F.broadcast(frames), "host", "left")
    else:
        salted = given.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALT)).cast("int"))
        joined = salted.join(frames.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1)))), ["host", "salt"], "left")
    joined = joined.select("page_id", "url", "html", "content", "boilerplate")

    def run(batches):
        for batch in batches:
            ids, urls, pages_, contents, boilers = batch.columns
            texts = [main_text(h or "", c, frozenset(b or ())) for h, c, b in zip(pages_.to_pylist(), contents.to_pylist(), boilers.to_pylist())]
            yield pa.RecordBatch.from_arrays(
                [ids, urls, pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64()), contents.is_valid()], ["page_id", "url", "text", "n_chars", "template"]
            )

    return joined.mapInArrow(run, "page_id long, url string, text string, n_chars long, template boolean")
