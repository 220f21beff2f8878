"""Main-text extraction by template deduction: tokens of equal occurrence vectors on a host's pages, and the slots between them.

A page is a stream of tokens: tags in their role (the path of open elements with name, class and id, as a hash) and text
nodes in theirs. Over the distinct pages of one host (copies and repeated rows are one page) every token has an
occurrence vector (its count on each page). Tokens with equal vectors form an equivalence class; a class is valid if it is
on enough pages and has not a single tag only. A role holds its path, so the elements of valid classes nest in one
another: together they are the host's template, and what lies between two of its tags is a slot.

Two things are read off the template. Fixed wording (text in a valid class) outside the content element leaves. And of
the elements that stand once on nearly every page, the innermost one that holds ``MOSTLY`` of the host's running text
(text that is no link) is the slot of the main text: where no article or main element marks the content, only this slot
counts, and it counts even if a word in its class or id speaks against it. Lists of tags and class words decide what is
left: which parts inside are menu, advert, notice, comment or the like, and hosts of fewer than ``LEAST_PAGES`` pages.
Text of a content element is always data, however many pages share it.

A vector is never gathered: its fingerprint, the sum over pages of count * hash(page), is additive, so a host
with a third of all pages is pre-aggregated in every task.
"""

from __future__ import annotations

import html as entities
import json
import re
from collections import Counter
from collections.abc import Iterator

import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import stored
from stseq.llm.urlrep import url_host

#: A text node or class is template if it is on this share of the host's pages, and on so many pages at least.
SUPPORT, LEAST_PAGES = 0.8, 4
#: Share of a host's running text that the slot of the main text holds at least.
MOSTLY = 0.9
#: Template rows that are broadcast; more are joined to the pages by host.
BROADCAST_ROWS = 500_000
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>?|</?[A-Za-z][^\s/>]*(?:\"[^\"]*\"|'[^']*'|[^>\"'])*>?|[^<]+|<", re.S)
_NAME = re.compile(r"</?([A-Za-z][^\s/>]*)")
_ATTR = re.compile(r"""([A-Za-z_:][-\w:.]*)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>"']+))?""")
_RAW = {"script", "style", "noscript", "template", "iframe", "svg", "textarea", "title", "math", "object", "canvas"}
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
_BLOCK = {
    "address", "article", "aside", "blockquote", "body", "caption", "center", "dd", "details", "dialog", "div", "dl", "dt", "fieldset",
    "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hgroup", "hr", "html", "li", "main", "nav",
    "ol", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul",
}
_CLOSES_P = _BLOCK - {"html", "body"}
_OFF_TAGS = {"nav", "footer", "aside", "form", "button", "select", "option", "dialog", "menu", "head", "label", "input"}
_OFF_WORDS = {
    "ad", "ads", "advert", "adverts", "advertisement", "advertising", "sponsor", "sponsored", "promo", "promotion", "banner", "cookie", "cookies",
    "consent", "gdpr", "notice", "notices", "alert", "popup", "modal", "overlay", "newsletter", "subscribe", "subscription", "sidebar", "menu", "nav", "navbar",
    "navigation", "breadcrumb", "breadcrumbs", "footer", "masthead", "comment", "comments", "disqus", "reply", "replies", "respond", "share",
    "sharing", "social", "related", "recommended", "recommendations", "widget", "toolbar", "pagination", "pager", "login", "signup", "search",
    "skip", "hidden", "copyright", "legal", "disclaimer", "contentinfo", "complementary",
}
#: Words that do not speak against an element inside of the content.
_ONLY_OUTSIDE = {"legal", "disclaimer", "search", "copyright", "contentinfo", "complementary", "login", "signup", "skip", "hidden", "related", "recommended"}
_CAMEL, _AROUND = re.compile(r"(?<=[a-z])(?=[A-Z])"), re.compile(r"\b(?:has|with|without|no)[-_]\w+", re.I)
_SPACE = re.compile(r"\s+")


class Element:
    """An open element: ``role`` hashes the path to it, ``label`` is its own part of it; ``mass`` counts running text in it.

    ``level``: 2 in a content element, 1 in the slot of the main text, else 0.
    """

    __slots__ = ("name", "role", "label", "depth", "off", "level", "link", "mass")

    def __init__(self, name: str, role: int, label: str, depth: int, off: bool, level: int, link: bool):
        self.name, self.role, self.label, self.depth, self.off, self.level, self.link, self.mass = name, role, label, depth, off, level, link, 0

    @property
    def content(self) -> bool:
        return self.level == 2


def _element(token: str, name: str, parent: Element, slot: int | None = None) -> Element:
    attrs = {}
    if len(token) > len(name) + 2:
        for m in _ATTR.finditer(token, len(name) + 1):
            attrs.setdefault(m[1].lower(), (m[2] or "").strip("\"'"))
    kind = " ".join(attrs[k] for k in ("class", "id", "role") if k in attrs)
    words = set(re.split(r"[^a-z0-9]+", _AROUND.sub("", _CAMEL.sub(" ", kind)).lower())) if kind else set()
    against = words & _OFF_WORDS - _ONLY_OUTSIDE if parent.content else words & _OFF_WORDS
    off = parent.off or name in _OFF_TAGS or bool(against) or "hidden" in attrs or attrs.get("aria-hidden") == "true"
    off = off or "display:none" in attrs.get("style", "").replace(" ", "").lower()
    if name == "header" and not parent.content or words & {"header"} and name != "h1" and not parent.content:
        off = True
    if name in ("html", "body") or name == "main" and not words & _OFF_WORDS:
        off = False
    label = f"{name}{'.' + re.sub(r'[0-9]+', '#', kind.lower()) if kind else ''}"
    role = xxhash.xxh64_intdigest(f"{parent.role}/{label}".encode("utf-8", "replace")) - (1 << 63)
    level = parent.level
    if slot is not None and role == slot:  # the template knows better than the word lists
        off, level = False, max(level, 1)
    if not off and (name in ("article", "main") or attrs.get("itemprop") == "articleBody" or attrs.get("role") == "main"):
        level = 2
    return Element(name, role, label, parent.depth + 1, off, level, parent.link or name == "a")


def walk(page: str, slot: int | None = None) -> Iterator[tuple[str, Element, str]]:
    """(kind, element, text) of a page in order; kind: open, close, text, break (an empty or void block). ``slot``: role of the main text.

    Open elements are counted by name, so that only names that are open are looked for: the time does not grow with the depth.
    """
    root = Element("", 0, "", 0, False, 0, False)
    stack, opened = [root], Counter()
    at, n = 0, len(page)

    def innermost(names) -> int:
        return next((d for d in range(len(stack) - 1, 0, -1) if stack[d].name in names), 0) if any(opened[x] for x in names) else 0

    def close(depth: int) -> Iterator[tuple[str, Element, str]]:
        while len(stack) > depth:
            e = stack.pop()
            opened[e.name] -= 1
            yield "close", e, ""
            stack[-1].mass += e.mass

    while at < n:
        m = _TOKEN.match(page, at)
        token, at = m[0], m.end()
        if token[0] != "<" or token == "<":
            yield "text", stack[-1], token
            continue
        tag = _NAME.match(token)
        if not tag:
            continue  # comment, doctype
        name = tag[1].lower()
        if token[1] == "/":
            depth = innermost((name,))
            if depth:
                yield from close(depth)
            elif name == "p":
                yield "break", stack[-1], ""
            continue
        if name in _CLOSES_P:
            depth = innermost(("p",))
            if depth and not any(e.name in _BLOCK for e in stack[depth + 1 :]):
                yield from close(depth)
            if name == "li":
                depth = innermost(("li", "ul", "ol"))
                if depth and stack[depth].name == "li":
                    yield from close(depth)
        if name in _RAW:
            if not token.endswith("/>"):
                end = re.compile(rf"</{re.escape(name)}\s*>?", re.I).search(page, at)
                at = end.end() if end else n
            continue
        e = _element(token, name, stack[-1], slot)
        if name in _VOID or token.endswith("/>"):
            yield ("break" if name in _BLOCK else "space"), e, ""
            continue
        yield "open", e, ""
        stack.append(e)
        opened[name] += 1
    yield from close(1)


def clean(text: str) -> str:
    return _SPACE.sub(" ", entities.unescape(text)).strip()


def _key(kind: str, role: int, text: str = "") -> int:
    return xxhash.xxh64_intdigest(f"{kind}\0{role}\0{text}".encode("utf-8", "replace")) - (1 << 63)


def page_tokens(page: str) -> tuple[Counter, dict[int, tuple]]:
    """Count of each token key on the page, and what keys stand for: (label, role, depth, running text) of an opening tag, with
    a label of "/" of a closing one, and with none of text. Text that is data or off is left out.
    """
    counts: Counter = Counter()
    about: dict[int, list] = {}
    for kind, e, text in walk(page):
        if kind == "text":
            if not (text := clean(text)):
                continue
            if not e.link and e.name not in _OFF_TAGS:
                e.mass += len(text)
            if e.off or e.content:
                continue
            k = _key("text", e.role, text)
            about.setdefault(k, ["", 0, 0, 0])
        elif kind == "open":
            k = _key("open", e.role)
            about.setdefault(k, [e.label, e.role, e.depth, 0])
        elif kind == "close":
            k = _key("close", e.role)
            about.setdefault(k, ["/" + e.label, e.role, e.depth, 0])
            if e.name not in _OFF_TAGS:
                about[_key("open", e.role)][3] += e.mass
            else:
                e.mass = 0
        else:
            continue
        counts[k] += 1
    return counts, about


def main_blocks(page: str, template: frozenset[int] | set[int], slot: int | None = None) -> list[str]:
    """Blocks of the page's main text: of its content elements, else of the slot, else all that is not off."""
    blocks: list[tuple[int, str]] = []
    parts: list[str] = []
    level = 0

    def flush():
        text = clean("".join(parts)) if parts else ""
        if text:
            blocks.append((level, text))
        parts.clear()

    for kind, e, text in walk(page, slot):
        if kind == "text":
            if e.off or (template and not e.content and _key("text", e.role, clean(text)) in template):
                continue
            if not parts:
                level = e.level
            parts.append(text)
        elif kind == "space":
            if e.name == "br" and parts:
                parts.append(" ")
        elif kind == "break" or e.name in _BLOCK:
            flush()
    flush()
    top = max((n for n, _ in blocks), default=0)
    return [b for n, b in blocks if n == top]


def deduce_templates(pages: DataFrame, support: float = SUPPORT, least: int = LEAST_PAGES) -> DataFrame:
    """Tokens of the valid equivalence classes of each host.

    host, token, class_id, label (null for text), role, depth, mass (running text in the element on all pages), pages, seen
    (occurrences), host_pages (pages are distinct ones). A class of tags is valid with both an opening and a closing token; a
    class of text alone is valid too (fixed wording outside of content elements). Tokens below the support are data of the slots.
    """

    def tokenise(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            got: dict[tuple[str, int], str] = {}
            for host, page in zip(f["host"], f["html"]):
                mark = xxhash.xxh64_intdigest((page or "").encode("utf-8", "replace"), 7) - (1 << 63)
                if (host, mark) not in got:
                    counts, about = page_tokens(page or "")
                    got[host, mark] = json.dumps([(k, n, *about[k]) for k, n in counts.items()])
            if got:
                yield pd.DataFrame({"host": [h for h, _ in got], "mark": [m for _, m in got], "tokens": list(got.values())})

    def count(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            # host, token -> pages, occurrences, vector fingerprint, mass, label, role, depth; host rows (token 0) count its pages
            got: dict[tuple[str, int], list] = {}
            for host, mark, tokens in zip(f["host"], f["mark"], f["tokens"]):
                got.setdefault((host, 0), [0, 0, 0, 0, "", 0, 0])[0] += 1
                for k, n, label, role, depth, mass in json.loads(tokens):
                    row = got.setdefault((host, k), [0, 0, 0, 0, label, role, depth])
                    row[0] += 1
                    row[1] += n
                    row[2] = (row[2] + n * (mark & 0xFFFFFFFF)) & ((1 << 62) - 1)
                    row[3] += mass
            if got:
                cols = list(zip(*got.values()))
                keys = list(got)
                names = ("pages", "seen", "vector", "mass", "label", "role", "depth")
                yield pd.DataFrame({"host": [h for h, _ in keys], "token": [t for _, t in keys]} | dict(zip(names, cols)))

    # each distinct page once: only its token counts are shuffled, not the page
    distinct = pages.select("host", "html").mapInPandas(tokenise, "host string, mark bigint, tokens string").dropDuplicates(["host", "mark"])
    rows = distinct.mapInPandas(count, "host string, token bigint, pages bigint, seen bigint, vector bigint, mass bigint, label string, role bigint, depth bigint")
    tokens = rows.groupBy("host", "token").agg(
        F.sum("pages").alias("pages"), F.sum("seen").alias("seen"), F.sum(F.col("vector").cast("decimal(38,0)")).alias("vector"), F.sum("mass").alias("mass"),
        F.max("label").alias("label"), F.max("role").alias("role"), F.max("depth").alias("depth"),
    )
    tokens = stored(tokens.withColumn("vector", (F.col("vector") % F.lit(1 << 62).cast("decimal(38,0)")).cast("long")), "tokens")
    sizes = tokens.where("token = 0").select("host", F.col("pages").alias("host_pages"))
    common = tokens.where("token <> 0").join(sizes, "host").where((F.col("pages") >= least) & (F.col("pages") >= support * F.col("host_pages")))
    tags = F.sum(F.when(F.col("label") != "", 1).otherwise(0))
    valid = common.groupBy("host", "vector", "pages", "seen").agg(tags.alias("tags"), F.count("*").alias("n")).where("tags <> 1")
    return common.join(valid.select("host", "vector", "pages", "seen"), ["host", "vector", "pages", "seen"]).select(
        "host", "token", F.xxhash64("vector", "pages", "seen").alias("class_id"), F.when(F.col("label") != "", F.col("label")).alias("label"),
        F.when(F.col("label") != "", F.col("role")).alias("role"), "depth", "mass", "pages", "seen", "host_pages",
    )


def main_slots(template: DataFrame, mostly: float = MOSTLY) -> DataFrame:
    """The role of the slot of each host's main text (host, slot): once on nearly every page, and the innermost with ``mostly`` of the running text."""
    # the label of a closing tag begins with a slash; only opening ones carry the mass
    elements = template.where("label is not null and left(label, 1) <> '/' and pages = seen and not label rlike '^(html|body)([.]|$)'")
    bodies = template.where("label rlike '^(html|body)([.]|$)'")
    whole = bodies.groupBy("host").agg(F.max("mass").alias("whole"))
    inner = elements.join(whole, "host").where((F.col("whole") > 0) & (F.col("mass") >= mostly * F.col("whole")))
    return inner.groupBy("host").agg(F.max_by("role", F.struct("depth", "mass", "role")).alias("slot"))


def extract_main(pages: DataFrame, support: float = SUPPORT, least: int = LEAST_PAGES, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """page_id, url, text, n_chars of every row: main blocks joined by an empty line; empty if there are none.

    A null page is empty; a null url belongs to the empty host; repeated rows stay.
    """
    keyed = pages.select("page_id", "url", url_host(F.col("url")).alias("host"), "html")
    template = stored(deduce_templates(keyed, support, least), "template")
    # a slot is one more row of its host, without a token
    rows = template.where("label is null").select("host", "token", F.lit(None).cast("bigint").alias("slot")).unionByName(
        main_slots(template).select("host", F.lit(None).cast("bigint").alias("token"), "slot")
    )

    def texts(f: pd.DataFrame, of) -> pd.DataFrame:
        text = ["\n\n".join(main_blocks(page or "", *of(i, host))) for i, (host, page) in enumerate(zip(f["host"], f["html"]))]
        return pd.DataFrame({"page_id": f["page_id"], "url": f["url"], "text": text, "n_chars": [len(t) for t in text]})

    out = f"page_id {pages.schema['page_id'].dataType.simpleString()}, url string, text string, n_chars bigint"
    if rows.count() <= broadcast_rows:
        known: dict[str, tuple[set[int], list[int]]] = {}
        for r in rows.toLocalIterator():
            fixed, slot = known.setdefault(r["host"], (set(), []))
            fixed.add(r["token"]) if r["slot"] is None else slot.append(r["slot"])
        shared = keyed.sparkSession.sparkContext.broadcast({h: (fixed, slot[0] if slot else None) for h, (fixed, slot) in known.items()})

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                yield texts(f, lambda i, host: shared.value.get(host, (frozenset(), None)))

        return keyed.mapInPandas(run, out)
    lists = rows.groupBy("host").agg(F.collect_list("token").alias("tokens"), F.max("slot").cast("string").alias("slot"))

    def run_joined(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            yield texts(f, lambda i, host: (
                set(f["tokens"].iloc[i]) if f["tokens"].iloc[i] is not None else frozenset(), int(f["slot"].iloc[i]) if f["slot"].iloc[i] is not None else None,
            ))

    return keyed.join(lists, "host", "left").mapInPandas(run_joined, out)
