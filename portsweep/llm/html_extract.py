"""Main text of web pages, by deducing the template that the pages of a host share.

A page is read as a sequence of tokens: one for every element, named by the path of elements it stands in, and one for
every text block, named by its path and its text. Over the distinct pages of a host each token has an occurrence vector:
how often it comes on each page. Tokens with equal vectors form an equivalence class; vectors are compared by a 64-bit
fingerprint that is summed up page by page, so a host's pages are never gathered. Every token stands inside the class of
the nearest element around it that is of another class; tokens of equal vectors are told apart by that outer class, so
that each class nests in one place of one other, and all of them make a tree. A class is template if the one around it is,
and if it stands on most of the host's pages or, for the layouts that only some pages have, also holds an element: then
its texts come exactly where that element comes.

Texts of template classes are the fixed parts and are cut; the texts between them are the slots. Of these, navigation,
notices, forms, adverts and comments are dropped by their element or its names; inside an article or main element a name
counts only as a whole, and only on a container. Slots inside an article or main element are the main content of a page
that has such slots; on other pages all are. A page without any slot, or whose marked content is all fixed, falls back to
its fixed texts.

Defined results: null html counts as empty and gives an empty text; a null or odd url belongs to the host named by an
empty string; repeated rows are extracted alike; copies of a page count once; extra columns, whatever their names, are
ignored; an empty table gives no rows; pages are read whole.
"""

from __future__ import annotations

import html as entities
import re
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, materialize, mix64, slices, with_columns_only

#: A class is template if its tokens stand on this share of a host's pages, in percent, or with an element of equal vector.
SUPPORT = 50
#: Fewer distinct pages than this do not tell fixed texts from others.
PAGES = 3

_TAG = re.compile(r"""<!--.*?(?:--!?>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)""", re.S)
_ATTRIBUTE = re.compile(r"""\b(class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_WORD = re.compile(r"[a-z]+")

# Kinds of HTML elements.
_RAW = {"script", "style", "noscript", "template", "textarea", "title", "iframe", "object", "svg", "math", "select", "noframes", "xmp"}
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
_INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "q", "ruby", "rb", "rp", "rt", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var"}
_CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"tr", "td", "th"}, "tbody": {"thead", "tr", "td", "th"}}
_AROUND = {"li": {"ul", "ol"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "tbody": {"table"}, "thead": {"table"}}
_BOILERPLATE = {"head", "nav", "header", "footer", "aside", "form", "button", "dialog", "menu", "fieldset"}
_BAD_NAMES = {"ad", "ads", "advert", "adverts", "advertisement", "advertising", "banner", "breadcrumb", "breadcrumbs", "comment", "comments", "consent", "cookie", "cookies", "disclaimer", "footer", "gdpr", "header", "masthead", "menu", "modal", "nav", "navbar", "navigation", "newsletter", "notice", "notices", "pagination", "popup", "promo", "promoted", "related", "reply", "replies", "share", "sharing", "sidebar", "social", "sponsor", "sponsored", "subscribe", "toolbar", "widget", "respond", "disqus", "complementary", "contentinfo", "search"}
_GOOD_NAMES = {"article", "main"}
#: Elements whose names still count inside an article or main element.
_CONTAINERS = {"div", "section", "aside", "ul", "ol", "dl", "table", "figure", "details"}
#: How deep classes nest at most.
_DEEPEST = 64


class Element:
    """A path of elements: its fingerprint, and whether it is main content or boilerplate by its names."""

    __slots__ = ("tag", "up", "key", "good", "bad")

    def __init__(self, tag: str, names: frozenset[str], whole: frozenset[str], up: Element | None):
        """names: the words of its class, id and role; whole: these values as they stand, parted at white space."""
        self.tag, self.up = tag, up
        self.key = xxhash.xxh3_64_intdigest(f"{up.key}/{tag}.{'.'.join(sorted(names))}") >> 1 if up else 0
        inside = bool(up and up.good)
        self.good = inside or tag in _GOOD_NAMES or "main" in names
        heading = tag == "header" and inside
        if inside:
            named = tag in _CONTAINERS and bool(whole & _BAD_NAMES)
        else:
            named = bool(names & _BAD_NAMES) and tag not in ("html", "body", "article", "main")
        self.bad = bool(up and up.bad) or (tag in _BOILERPLATE and not heading) or named


class Reader:
    """Reads pages; paths are kept for reuse by one worker."""

    def __init__(self) -> None:
        self.root = Element("", frozenset(), frozenset(), None)
        self.known: dict[tuple[int, str, str], Element] = {}

    def _child(self, up: Element, tag: str, attributes: str) -> Element:
        named = attributes if "=" in attributes and tag not in _INLINE else ""
        found = self.known.get((up.key, tag, named))
        if found is None:
            values = [(m[2] or m[3] or m[4] or "").lower() for m in _ATTRIBUTE.finditer(named)] if named else []
            names, whole = frozenset(w for v in values for w in _WORD.findall(v)), frozenset(w for v in values for w in v.split())
            if len(self.known) > 100_000:
                self.known.clear()
            found = self.known[up.key, tag, named] = Element(tag, names, whole, up)
        return found

    def read(self, page: str) -> tuple[list[Element], list[tuple[Element, str]]]:
        """The elements of a page in order, and its text blocks with the innermost block element around each."""
        seen: list[Element] = []
        blocks: list[tuple[Element, str]] = []
        at, stack, held = 0, [self.root], []

        def flush() -> None:
            if held:
                text = " ".join(entities.unescape("".join(held)).split())
                if text:
                    blocks.append((stack[-1], text))
                held.clear()

        while True:
            m = _TAG.search(page, at)
            end = m.start() if m else len(page)
            if end > at:
                held.append(page[at:end])
            if not m:
                break
            at = m.end()
            tag = m[2] or m[5]
            if not tag:
                continue
            tag, closing, attributes = tag.lower(), bool(m[1] or m[4]), m[3] or m[6] or ""
            if tag == "br":
                held.append(" ")
                continue
            if tag in _VOID:
                if tag == "hr":
                    flush()
                continue
            if tag in _INLINE:
                continue
            if tag in _RAW:
                if not closing:
                    found = re.compile(rf"</{tag}(?=[\s/>])[^>]*(?:>|\Z)", re.I).search(page, at)
                    at = found.end() if found else len(page)
                continue
            flush()
            if closing:
                for depth in range(len(stack) - 1, 0, -1):
                    if stack[depth].tag == tag:
                        del stack[depth:]
                        break
                continue
            if stack[-1].tag == "p":
                stack.pop()
            if tag in _CLOSES:
                for depth in range(len(stack) - 1, 0, -1):
                    if stack[depth].tag in _AROUND.get(tag, ()):
                        break
                    if stack[depth].tag in _CLOSES[tag]:
                        del stack[depth:]
            element = self._child(stack[-1], tag, attributes)
            seen.append(element)
            if not attributes.rstrip().endswith("/"):
                stack.append(element)
        flush()
        return seen, blocks


def _token(e: Element, text: str) -> int:
    return xxhash.xxh3_64_intdigest(text.encode("utf-8", "surrogatepass"), e.key) >> 1


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """host, token, up (the element around it), element, page, part: one row per page and token, page and part being hashes of its html and of that with the count."""
    reader = Reader()
    for b in slices(batches):
        hosts, cols, elements = [], [[], [], [], []], []
        for host, page in zip(b.column("host").to_pylist(), b.column("html"), strict=True):
            page = page.as_py() or ""
            seen, blocks = reader.read(page)
            mark = xxhash.xxh3_64_intdigest(page.encode("utf-8", "surrogatepass")) >> 1
            times: dict[tuple[int, int, bool], int] = defaultdict(int)
            for e in [reader.root, *seen]:
                times[e.key, e.up.key if e.up else 0, True] += 1
            for e, text in blocks:
                times[_token(e, text), e.key, False] += 1
            for (token, up, element), n in times.items():
                hosts.append(host)
                elements.append(element)
                for c, x in zip(cols, (token, up, mark, n), strict=True):
                    c.append(x)
        token, up, mark, n = (np.array(c, np.uint64) for c in cols)
        part = mix64(mark * np.uint64(3) + n)
        arrays = [pa.array(hosts, pa.string()), *[pa.array(x.view(np.int64)) for x in (token, up)], pa.array(elements, pa.bool_()), *[pa.array(x.view(np.int64)) for x in (mark, part)]]
        yield pa.RecordBatch.from_arrays(arrays, ["host", "token", "up", "element", "page", "part"])


def classes(pages: DataFrame) -> DataFrame:
    """host, token, element, pages, vector, outer_pages, outer_vector, outer_token (a token of the class around it; null: none): tokens of PAGES distinct pages or more."""
    counted = pages.mapInArrow(_count, "host string, token bigint, up bigint, element boolean, page bigint, part bigint")
    once = counted.groupBy("host", "token", "element", "page").agg(F.max("part").alias("part"), F.max("up").alias("up"))  # copies of a page have equal parts
    tokens = once.groupBy("host", "token", "element").agg(F.count("*").alias("pages"), F.bit_xor("part").alias("vector"), F.max("up").alias("up"))
    tokens = materialize(tokens.where(F.col("pages") >= PAGES), "tokens")
    around = tokens.where("element").select("host", F.col("token").alias("at"), F.col("up").alias("next"), F.col("pages").alias("p"), F.col("vector").alias("v"))
    open_, done = tokens.withColumn("at", F.when(~F.col("element") | (F.col("token") != 0), F.col("up"))), []
    for _ in range(_DEEPEST):
        met = open_.join(around, ["host", "at"], "left")
        same = (F.col("p") == F.col("pages")) & (F.col("v") == F.col("vector")) & (F.col("at") != 0)
        met = materialize(met.withColumn("same", F.coalesce(same, F.lit(False))), "around")
        alike = (F.col("p") == F.col("pages")) & (F.col("v") == F.col("vector"))
        none = F.col("p").isNull() | alike  # it is of the outermost class
        done.append(met.where("not same").select("host", "token", "element", "pages", "vector", *[F.when(~none, F.col(c)).alias(n) for c, n in (("p", "outer_pages"), ("v", "outer_vector"), ("at", "outer_token"))]))
        open_ = met.where("same").withColumn("at", F.col("next")).drop("next", "p", "v", "same")
        if open_.isEmpty():
            break
    out = done[0]
    for d in done[1:]:
        out = out.union(d)
    return materialize(out, "classes")


def templates(pages: DataFrame) -> DataFrame:
    """host, fixed: the text tokens of each host that are template."""
    every = classes(pages)
    name = ["host", "pages", "vector", "outer_pages", "outer_vector"]
    whole = every.where("element and token = 0").select("host", F.col("pages").alias("all_pages"))
    made = every.groupBy(*name).agg(F.max("element").alias("framed"), F.max("outer_token").alias("outer_token"))
    made = made.join(whole, "host")
    own = (100 * F.col("pages") >= SUPPORT * F.col("all_pages")) | F.col("framed")
    made = materialize(made.withColumn("own", own), "class-list")
    of = every.where("element").select("host", F.col("token").alias("outer_token"), F.col("outer_pages").alias("next_pages"), F.col("outer_vector").alias("next_vector"))
    # A class is named by its vector and its outer class; the outer class's own name is found through one of its tokens.
    linked = made.join(of, ["host", "outer_token"], "left")
    ok, kept = materialize(linked.where("own and outer_pages is null").select(*name), "template"), []
    for _ in range(_DEEPEST):
        kept.append(ok)
        above = ok.select("host", F.col("pages").alias("a"), F.col("vector").alias("b"), F.col("outer_pages").alias("c"), F.col("outer_vector").alias("d"))
        inner = linked.alias("x").join(above.alias("y"), (F.col("x.host") == F.col("y.host")) & (F.col("x.outer_pages") == F.col("a")) & (F.col("x.outer_vector") == F.col("b")) & F.col("x.next_pages").eqNullSafe(F.col("c")) & F.col("x.next_vector").eqNullSafe(F.col("d")))
        ok = materialize(inner.where("own").select(*[F.col(f"x.{n}") for n in name]), "template")
        if ok.isEmpty():
            break
    good = kept[0]
    for k in kept[1:]:
        good = good.union(k)
    texts = every.where("not element").alias("t").join(good.alias("g"), (F.col("t.host") == F.col("g.host")) & (F.col("t.pages") == F.col("g.pages")) & (F.col("t.vector") == F.col("g.vector")) & F.col("t.outer_pages").eqNullSafe(F.col("g.outer_pages")) & F.col("t.outer_vector").eqNullSafe(F.col("g.outer_vector")), "left_semi")
    return texts.groupBy("host").agg(F.collect_set("token").alias("fixed"))


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    reader = Reader()
    for b in slices(batches):
        texts = []
        sets: dict[str, frozenset] = {}
        for host, page, fixed in zip(b.column("host").to_pylist(), b.column("html"), b.column("fixed"), strict=True):
            if host not in sets:
                sets[host] = frozenset(fixed.as_py() or ())
            clear = [(e.good, _token(e, text) in sets[host], text) for e, text in reader.read(page.as_py() or "")[1] if not e.bad]
            if any(good for good, _, _ in clear):
                clear = [x for x in clear if x[0]]
            slots = [text for _, held, text in clear if not held]
            texts.append("\n\n".join(slots or [text for _, _, text in clear]))
        yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars: one row per row of pages."""
    p = with_columns_only(pages, "page_id", "url", "html").withColumn("page_id", F.col("page_id").cast("bigint"))
    host = F.lower(F.regexp_extract(F.coalesce("url", F.lit("")), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1))
    p = p.withColumn("host", host)
    found = materialize(templates(p), "templates").withColumnRenamed("host", "__host")
    hosts, texts = found.agg(F.count("*"), F.sum(F.size("fixed"))).first()
    if hosts * 200 + (texts or 0) * 8 <= BROADCAST_BYTES:
        found = F.broadcast(found)
    joined = p.join(found, F.col("host") == F.col("__host"), "left").select("page_id", "url", "html", "host", "fixed")
    return joined.mapInArrow(_cut, "page_id bigint, url string, text string, n_chars bigint")
