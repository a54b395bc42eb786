"""Main-text extraction by wrapper inference (operator 1).

A host's pages are aligned with one another into a wrapper: a union-free regular expression over the token
streams, kept as a tree.  Where two streams agree the token stays; a token that only some have becomes
optional; neighbouring repeats of a run of elements become one repeated group; text that differs becomes a
slot, text that never differs is template.  Each task folds its own pages host by host, the partial
wrappers of a host are merged, and the host's wrapper then says for each place whether its text is main
text.  Three things follow from the wrapper: where the content lies (the article or main element that a page has, else
the element that holds most of the text in slots); which text there is template, since all pages that have the place
have this very text; and which lists are menus, since nearly all their text is links.  What the wrapper leaves open,
variable text beside the article's own, is judged by tag, role and name: menus, headers, footers, sidebars, notices,
adverts, forms and comments go.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared, slices

#: Elements nested deeper than this are read as if their tags were absent.
DEPTH = 100
#: Longest run of elements that is looked for as a repeated group.
PERIOD = 4
#: Pages that must agree before unchanging text counts as none of a place's content, and as template inside the content.
SAME_PAGES, TEMPLATE_PAGES = 3, 8
#: Share of link text from which a list is a menu.
MENU_LINKS = 0.8
#: Bytes of wrappers that may be broadcast; beyond, pages are dealt over ``SALTS`` groups a host.
BESIDE_BYTES, SALTS = 64 << 20, 16
_LCS = 250_000

# Fixed values of HTML.
_RAW = "script|style|noscript|template|svg|math|iframe|object|textarea|select|head|title|canvas|audio|video"
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
_CLOSES = {"p": {"p"}, "li": {"li", "p"}, "dt": {"dt", "dd", "p"}, "dd": {"dt", "dd", "p"}, "tr": {"tr", "td", "th", "p"}, "td": {"td", "th", "p"}, "th": {"td", "th", "p"}, "option": {"option"}}
_HOLDS = frozenset("ul ol dl table tbody thead article section div main aside nav body blockquote form".split())
_OUT_TAGS = frozenset("nav footer aside form button menu dialog fieldset datalist script style head title noscript".split())
_OUT_ROLES = frozenset("navigation banner complementary contentinfo search form dialog alert alertdialog menu menubar toolbar tooltip".split())
_OUT_WORDS = re.compile(
    r"(?:ads?|adv|advert\w*|adsense|banner\w*|promo\w*|sponsor\w*|cookies?|consent|gdpr|notices?|alerts?|popups?|modal|overlay|newsletter|subscri\w*|signup|login|social|share|sharing|follow|related|recommend\w*"
    r"|sidebars?|sidenav|rail|menus?|nav|navbar|navigation|breadcrumbs?|footer|foot|masthead|topbar|toolbar|comments?|commentlist|disqus|respond|replies|reply|reviews?|widgets?|pagination|pager|copyright|disclaimer|skip|search|form)"
)
_TOKEN = re.compile(
    rf"<!--.*?(?:-->|\Z)|<(?P<raw>{_RAW})\b(?:[^>\"']|\"[^\"]*\"|'[^']*')*?(?:/>|>.*?(?:</(?P=raw)\s*>|\Z))|<(?P<end>/?)(?P<name>[a-z][^\s/>]*)(?P<attrs>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?/][^>]*(?:>|\Z)|(?P<text>[^<]+|<)",
    re.I | re.S,
)
_ATTR = re.compile(r"""([a-z-]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I)


@dataclass(slots=True)
class Node:
    """An element, or a run of text (label ``#``)."""

    label: str
    children: list[Node] = field(default_factory=list)
    text: str = ""
    links: int = 0


def _label(name: str, attrs: str) -> str:
    """name.classes#id@role; ``!`` marks hidden elements."""
    if not attrs.strip(" /\t\r\n"):
        return name
    found = {m[1].lower(): (m[2] or m[3] or m[4] or "") for m in _ATTR.finditer(attrs)}
    style = found.get("style", "").replace(" ", "").lower()
    hidden = "hidden" in found or found.get("aria-hidden") == "true" or "display:none" in style
    classes = re.sub(r"\d+", "0", " ".join(found.get("class", "").split()))
    return f"{name}.{classes}#{re.sub(r'[0-9]+', '0', found.get('id', ''))}@{found.get('role', '').lower()}" + "!" * hidden


def parse(html: str) -> Node:
    """Tree of a page's block elements; inline tags and line breaks only leave their text."""
    root = Node("")
    stack, names = [root], [""]
    run: list[str] = []
    links = depth_a = 0

    def flush() -> None:
        nonlocal links
        if run:
            text = " ".join("".join(run).split())
            if text:
                stack[-1].children.append(Node("#", text=text, links=min(links, len(text))))
            run.clear()
        links = 0

    for m in _TOKEN.finditer(html):
        if (text := m["text"]) is not None:
            text = unescape(text)
            run.append(text)
            if depth_a:
                links += len(text.strip())
            continue
        if (name := m["name"]) is None:
            continue
        name = name.lower()
        if name in _INLINE:
            if name == "a":
                depth_a = max(0, depth_a + (-1 if m["end"] else 1))
            elif name == "br":
                run.append(" ")
            continue
        flush()
        depth_a = 0
        if m["end"]:
            if name in names[1:]:
                at = len(names) - 1 - names[::-1].index(name)
                if name != "p" or not _HOLDS & set(names[at:]):
                    del stack[at:], names[at:]
            continue
        closes = _CLOSES.get(name, {"p"} if name not in _VOID else ())
        at = len(names) - 1
        while at and names[at] not in _HOLDS:
            if names[at] in closes:
                del stack[at:], names[at:]
            at -= 1
            at = min(at, len(names) - 1)
        if name in _VOID or m["attrs"].endswith("/") and name not in _HOLDS or len(stack) > DEPTH:
            continue
        node = Node(_label(name, m["attrs"]))
        stack[-1].children.append(node)
        stack.append(node)
        names.append(name)
    flush()
    return root


@dataclass(slots=True)
class Part:
    """A piece of a wrapper: an element, a group ``(...)`` of elements, or text ``#``.

    ``fixed``: digest of a text that all pages share, None for a slot.  ``chars`` and ``links`` add up over pages.
    """

    label: str
    optional: bool = False
    repeated: bool = False
    fixed: int | None = None
    chars: int = 0
    links: int = 0
    pages: int = 1
    children: list[Part] = field(default_factory=list)

    def dump(self) -> list:
        return [self.label, int(self.optional), int(self.repeated), self.fixed, self.chars, self.links, self.pages, [x.dump() for x in self.children]]

    @classmethod
    def load(cls, data: list) -> Part:
        return cls(data[0], bool(data[1]), bool(data[2]), *data[3:7], [cls.load(x) for x in data[7]])

    def expression(self) -> str:
        """The wrapper as a regular expression over tags and text."""
        inner = "".join(x.expression() for x in self.children)
        name = re.split(r"[.#@!]", self.label)[0]
        own = ("#text" if self.fixed is None else "'fixed'") if self.label == "#" else inner if self.label.startswith("(") else f"<{name}>{inner}</{name}>"
        return f"({own})" + ("+" if self.repeated else "") + ("?" if self.optional else "") if self.repeated or self.optional else own


def _merge(a: Part, b: Part, same_page: bool = False) -> Part:
    """What both match; ``same_page``: repeats within one page."""
    fixed = a.fixed if a.fixed == b.fixed else None
    pages = max(a.pages, b.pages) if same_page else a.pages + b.pages
    return Part(a.label, a.optional or b.optional, a.repeated or b.repeated, fixed, a.chars + b.chars, a.links + b.links, pages, align(a.children, b.children, same_page))


def align(a: list[Part], b: list[Part], same_page: bool = False) -> list[Part]:
    """One sequence for two: common parts merge, parts that only one has become optional."""
    x, y = [p.label for p in a], [p.label for p in b]
    if x == y:
        return [_merge(p, q, same_page) for p, q in zip(a, b, strict=True)]
    pairs, out = _common(x, y), []
    i = j = 0
    for p, q in [*pairs, (len(a), len(b))]:
        for part in [*a[i:p], *b[j:q]]:
            part.optional = True
            out.append(part)
        if p < len(a):
            out.append(_merge(a[p], b[q], same_page))
        i, j = p + 1, q + 1
    return fold(out, same_page)


def _common(x: list[str], y: list[str]) -> list[tuple[int, int]]:
    """Longest common subsequence; for very long sequences the next common label each time."""
    n, m = len(x), len(y)
    if n * m > _LCS:
        out, j = [], 0
        for i, label in enumerate(x):
            if label in y[j:]:
                j = y.index(label, j) + 1
                out.append((i, j - 1))
        return out
    best = [[0] * (m + 1) for _ in range(n + 1)]
    for i in range(n - 1, -1, -1):
        for j in range(m - 1, -1, -1):
            best[i][j] = best[i + 1][j + 1] + 1 if x[i] == y[j] else max(best[i + 1][j], best[i][j + 1])
    out, i, j = [], 0, 0
    while i < n and j < m:
        if x[i] == y[j]:
            out.append((i, j))
            i, j = i + 1, j + 1
        elif best[i + 1][j] >= best[i][j + 1]:
            i += 1
        else:
            j += 1
    return out


def fold(parts: list[Part], same_page: bool = True) -> list[Part]:
    """Neighbouring repeats of up to ``PERIOD`` parts become one repeated part or group."""
    out: list[Part] = []
    for part in parts:
        out.append(part)
        again = True
        while again:
            again = False
            for n in range(1, PERIOD + 1):
                tail = [p.label for p in out[-n:]]
                if n > 1 and len(out) > n and out[-n - 1].label == "(" + ",".join(tail) + ")":
                    group = out[-n - 1]
                    group.children = [_merge(p, q, True) for p, q in zip(group.children, out[-n:], strict=True)]
                    del out[-n:]
                    again = True
                elif len(out) >= 2 * n and [p.label for p in out[-2 * n : -n]] == tail:
                    merged = [_merge(p, q, True) for p, q in zip(out[-2 * n : -n], out[-n:], strict=True)]
                    del out[-2 * n :]
                    if n == 1:
                        merged[0].repeated = True
                        out.append(merged[0])
                    else:
                        out.append(Part("(" + ",".join(tail) + ")", repeated=True, pages=max(p.pages for p in merged), children=merged))
                    again = True
                if again:
                    break
    return out


def wrapper_of(node: Node) -> Part:
    """A single page's wrapper."""
    if node.label == "#":
        return Part("#", fixed=digest(node.text), chars=len(node.text), links=node.links)
    return Part(node.label, children=fold([wrapper_of(x) for x in node.children]))


def _named(label: str) -> tuple[str, str, str, str, bool]:
    hidden = label.endswith("!")
    rest, _, role = label.rstrip("!").partition("@")
    rest, _, ident = rest.partition("#")
    name, _, classes = rest.partition(".")
    return name, classes, ident, role, hidden


def unwanted(label: str, in_article: bool) -> bool:
    """Whether an element is no place of main text, by its tag, role, class and id."""
    name, classes, ident, role, hidden = _named(label)
    if hidden or name in _OUT_TAGS or role in _OUT_ROLES or name == "header" and not in_article:
        return True
    if name in ("html", "body", "article", "main", "h1") and not re.search(r"\bcomment", classes):
        return False
    for word in re.split(r"[^A-Za-z]+", re.sub(r"(?<=[a-z])(?=[A-Z])", "-", f"{classes} {ident}")):
        if _OUT_WORDS.fullmatch(word.lower()) or word.lower() == "header" and not in_article:
            return True
    return False


def _variable(part: Part) -> int:
    """Characters of slots that are no links."""
    if part.label == "#":
        return max(0, part.chars - 2 * part.links) if part.fixed is None or part.pages < SAME_PAGES else 0
    return sum(map(_variable, part.children))


@dataclass
class Decisions:
    """What a host's wrapper says: the paths of its content, the texts that are template at a path, the paths of menus."""

    roots: set[tuple[str, ...]]
    template: set[tuple[tuple[str, ...], int]]
    menus: set[tuple[str, ...]]

    @classmethod
    def of(cls, wrapper: Part) -> Decisions:
        out = cls(_roots(wrapper), set(), set())
        slots = _variable(wrapper) > 0  # pages that are all alike tell nothing of templates

        def walk(part: Part, path: tuple[str, ...], listed: bool) -> None:
            if not part.label.startswith("("):
                path = (*path, part.label)
            listed = listed or _named(part.label)[0] in ("ul", "ol", "dl", "menu")
            if part.label == "#" and part.pages >= TEMPLATE_PAGES:
                if slots and part.fixed is not None and not part.repeated:
                    out.template.add((path, part.fixed))
                if listed and part.links >= MENU_LINKS * part.chars:
                    out.menus.add(path)
            for child in part.children:
                walk(child, path, listed)

        walk(wrapper, (), False)
        return out


def _roots(wrapper: Part) -> set[tuple[str, ...]]:
    """Paths of the articles, else of the main element, else of the element with most of the variable text."""
    found: dict[str, set[tuple[str, ...]]] = {"article": set(), "main": set()}

    def walk(part: Part, path: tuple[str, ...]) -> None:
        if part.label.startswith("("):
            for child in part.children:
                walk(child, path)
        elif part.label != "#" and not unwanted(part.label, False):
            path = (*path, part.label)
            name, _, _, role, _ = _named(part.label)
            if name in found or role in found:
                found[name if name in found else role].add(path)
            for child in part.children:
                walk(child, path)

    walk(wrapper, ())
    if found["article"] or found["main"]:
        return found["article"] or found["main"]
    path, part = (wrapper.label,), wrapper
    while True:
        parts = [x for c in part.children for x in (c.children if c.label.startswith("(") else [c])]
        total = sum(_variable(x) for x in parts if x.label == "#" or not unwanted(x.label, False))
        best = max((x for x in parts if x.label != "#" and not unwanted(x.label, False)), key=_variable, default=None)
        if best is None or _variable(best) < 0.6 * total or _named(best.label)[0] in ("p", "li", "td", "h1", "h2", "blockquote", "pre"):
            return {path}
        path, part = (*path, best.label), best


def digest(text: str) -> int:
    return zlib.crc32(text.encode())


def main_text(node: Node, decisions: Decisions) -> str:
    """Main text of a page by its host's wrapper.

    A page that has none of the wrapper's content places is searched for its own; one whose content is all template (a
    page that its host repeats) keeps it.
    """
    paths: set[tuple[str, ...]] = set()

    def seen(at: Node, path: tuple[str, ...]) -> None:
        paths.add(path := (*path, at.label))
        for child in at.children:
            seen(child, path)

    seen(node, ())
    roots = (decisions.roots & paths) or _roots(wrapper_of(node))
    blocks: list[str] = []
    fixed: list[str] = []

    def walk(at: Node, path: tuple[str, ...], inside: bool, out: bool) -> None:
        path = (*path, at.label)
        if at.label == "#":
            if inside and not out and path not in decisions.menus:
                fixed.append(at.text)
                if (path, digest(at.text)) not in decisions.template:
                    blocks.append(at.text)
            return
        inside = inside or path in roots
        out = out or unwanted(at.label, inside)
        for child in at.children:
            walk(child, path, inside, out)

    walk(node, (), False, False)
    return "\n".join(blocks or fixed)


_HOST = r"^(?i:[a-z][a-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)"
_WRAPPER = "host string, wrapper string"


def host(url: str) -> F.Column:
    return F.lower(F.regexp_extract(F.coalesce(F.col(url), F.lit("")), _HOST, 1))


def _fold_pages(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Wrappers of the hosts of a task's pages; handed on whenever many are held."""
    held: dict[str, Part] = {}
    for batch, texts in slices(batches, "html"):
        for name, html in zip(batch.column("host").to_pylist(), texts, strict=True):
            own = wrapper_of(parse(html.decode()))
            held[name] = _merge(held[name], own) if name in held else own
        if len(held) > 5000:
            yield _dumped(held)
            held = {}
    yield _dumped(held)


def _dumped(held: dict[str, Part]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(list(held), pa.string()), pa.array([json.dumps(x.dump()) for x in held.values()], pa.string())], ["host", "wrapper"])


def _merge_hosts(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Partial wrappers sorted by host, merged host by host."""
    now: str | None = None
    part: Part | None = None
    for batch in batches:
        done: dict[str, Part] = {}
        for name, text in zip(batch.column("host").to_pylist(), batch.column("wrapper").to_pylist(), strict=True):
            own = Part.load(json.loads(text))
            if part is not None and name == now:
                part = _merge(part, own)
            else:
                if part is not None:
                    done[now] = part  # type: ignore[index]
                now, part = name, own
        yield _dumped(done)
    if part is not None:
        yield _dumped({now: part})  # type: ignore[dict-item]


def infer(pages: DataFrame) -> DataFrame:
    """``host``, ``wrapper`` (JSON of a ``Part``) of every host, from all its pages."""
    partial = pages.select(host("url").alias("host"), "html").where("html is not null").mapInArrow(_fold_pages, _WRAPPER)
    return partial.repartition("host").sortWithinPartitions("host", "wrapper").mapInArrow(_merge_hosts, _WRAPPER)


_DECISIONS: dict[str, Decisions] = {}


def _decisions(wrapper: str | None) -> Decisions:
    if wrapper is None:
        return Decisions(set(), set(), set())
    if (found := _DECISIONS.get(wrapper)) is None:
        if len(_DECISIONS) >= 2000:
            _DECISIONS.clear()
        found = _DECISIONS[wrapper] = Decisions.of(Part.load(json.loads(wrapper)))
    return found


def _with_wrappers(pages: DataFrame, wrappers: Shared) -> DataFrame:
    """Pages (``_h``: host) beside their host's wrapper: broadcast if all wrappers together are small, else joined with each host's pages dealt over groups."""
    held = wrappers.frame.withColumnRenamed("host", "_host")
    if (held.agg(F.sum(F.octet_length("wrapper"))).first()[0] or 0) <= BESIDE_BYTES:
        return pages.join(F.broadcast(held), F.col("_h") == F.col("_host"), "left")
    salt = F.pmod(F.xxhash64("page_id", "url", F.length("html")), F.lit(SALTS))
    copies = held.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return pages.withColumn("_s", salt).join(copies, (F.col("_h") == F.col("_host")) & (F.col("_s") == F.col("_salt")), "left")


def extract(pages: DataFrame) -> DataFrame:
    """``page_id``, ``url``, ``text``, ``n_chars`` of every page: its main text, blocks joined by one line break.

    Null html is empty, a null url is a host of its own (the empty one), repeated rows give repeated results; further
    columns are left out, whatever their names; an empty table gives an empty result.
    """
    own = pages.select(F.col("page_id").cast("long"), "url", "html")
    wrappers = Shared(infer(own), "wrappers")
    joined = _with_wrappers(own.withColumn("_h", host("url")), wrappers).select("page_id", "url", "html", "wrapper")

    def work(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in slices(batches, "html"):
            found = [main_text(parse(t.decode()), _decisions(w)) if t else "" for t, w in zip(texts, batch.column("wrapper").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(found, pa.string()), pa.array([len(x) for x in found], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return joined.mapInArrow(work, "page_id long, url string, text string, n_chars long")
