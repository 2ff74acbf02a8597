"""Main text of web pages by wrappers inferred per host.

A page becomes a sequence of groups: texts in a row with the same path, and rows of paths that come
again, are one repeated group.  Pages of a host whose groups agree are merged wherever they are read,
and the merged ones are aligned per template: texts of a group that every page has stay fixed, the
others are slots, and groups that only some pages have are optional.  Only then is a repeated group
a slot, so texts that agree inside one stay fixed.  Pages belong to the template that half of their
groups agree with, and each template of a host has a wrapper of its own, inferred from all its pages.

The wrapper tells the template's fixed texts, dropped inside articles too but for headings, from its
slots, which are the text; slots in a container of navigation, notices, adverts, forms, comments and
the like are none.  When a page has an article or main element, only what is inside counts, unless more
than twice as much content stands outside: then the element is a teaser.  Pages
whose article would lose over half of its characters are copies of one article, so theirs is kept.
Templates with fewer than ``LEAST_PAGES`` different pages have no fixed texts.

Defined results: null and empty pages have an empty text; markup that never closes ends with the
page; a null url is a host of its own; repeated rows give equal rows; an empty table gives no rows.
"""

from __future__ import annotations

import difflib
import hashlib
import html
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.llm.common import staged, table
from narrative_engine.shipping import ship

LEAST_PAGES = 3
HELD = 2_000  # merged pages that a worker holds before it passes them on
BROADCAST_HOSTS = 100_000

#: Elements by what they do to text.
RAW = frozenset("script style noscript template iframe textarea title svg math object canvas audio video select datalist option head".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q ruby rt rp s samp small span strike strong sub sup time tt u var wbr br img".split())
ASIDE = frozenset("nav header footer aside form button dialog menu fieldset".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6 hgroup".split())
CLOSED_BY = {"p": frozenset("p div ul ol dl table h1 h2 h3 h4 h5 h6 section article blockquote pre form header footer nav aside main hr address figure".split()), "li": frozenset(["li"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"]), "tr": frozenset(["tr", "tbody"]), "td": frozenset(["td", "th", "tr"]), "th": frozenset(["td", "th", "tr"]), "option": frozenset(["option"])}
#: Words of class, id and role that name something other than the article.
OTHER = re.compile(
    r"(?:^|[\s_-])(?:ad|ads|adv|advert\w*|sponsor\w*|promo\w*|banner\w*|nav\w*|menu\w*|breadcrumbs?|sidebar\w*|side|widget\w*|related\w*|recommend\w*|comments?|commentlist|"
    r"replies|reply|respond|disqus\w*|footer\w*|foot|masthead\w*|topbar|toolbar|cookies?|consent\w*|gdpr|notices?|notification\w*|alert\w*|popup\w*|modal\w*|overlay\w*|subscri\w*|"
    r"newsletter\w*|signup|sign-up|login|share\w*|sharing|social\w*|search\w*|pagination|pager|copyright|legal|disclaimer|hidden|sr-only|skip\w*|complementary|contentinfo|navigation|"
    r"dialog|form|site-header|page-header|header)(?=$|[\s_-]|\d)", re.I)  # fmt: skip
#: Inside an article only whole names count, and only those that name no kind of prose.
OTHER_INSIDE = re.compile(
    r"(?:^|\s)(?:ads?|adv|advert|advertisements?|sponsor(?:ed)?|promo|promos|promoted|banner|nav|navbar|navigation|menu|breadcrumbs?|sidebar|widget|related|related-(?:posts|articles|links)|recommended|"
    r"comments?|comment-list|commentlist|replies|disqus|cookies?|cookie-(?:notice|banner)|consent|gdpr|notice|notices|popup|modal|overlay|subscribe|subscription|newsletter|newsletter-signup|signup|sign-up|"
    r"share|shares|sharing|share-(?:bar|buttons)|social|social-(?:bar|links|share)|search|pagination|pager|hidden|sr-only)(?=$|\s)", re.I)  # fmt: skip
NO_ARTICLE = re.compile(r"(?:^|[\s_\"'=-])(?:comments?|repl(?:y|ies)|related|promo\w*|sponsor\w*|ad|advert\w*)(?=$|[\s_\"'-])", re.I)
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([A-Za-z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
ATTRIBUTE = re.compile(r"(?:^|\s)(class|id|role|aria-hidden|hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)


@dataclass
class Element:
    name: str
    other: bool  # here or above
    inside: bool  # an article or main element here or above


@dataclass(frozen=True)
class Block:
    text: str
    other: bool
    inside: bool
    path: str


def named_other(attributes: str, inside: bool) -> bool:
    """Whether class, id or role tell of something else."""
    names = OTHER_INSIDE if inside else OTHER
    for m in ATTRIBUTE.finditer(attributes):
        key, value = m[1].lower(), m[2] or m[3] or m[4] or ""
        if key == "hidden" or key == "aria-hidden" and value.lower() == "true" or key in ("class", "id", "role") and names.search(value):
            return True
    return False


def blocks(page: str) -> list[Block]:
    """The texts of a page, one per block, with where they stand."""
    out: list[Block] = []
    stack: list[Element] = []
    parts: list[str] = []

    def flush() -> None:
        text = " ".join(html.unescape("".join(parts)).split())
        parts.clear()
        if text:
            top = stack[-1] if stack else Element("", False, False)
            out.append(Block(text, top.other, top.inside, "/".join(e.name for e in stack if e.name not in INLINE)))

    at, end = 0, len(page)
    while at < end:
        m = TOKEN.search(page, at)
        if m is None:
            parts.append(page[at:])
            break
        if m.start() > at:
            parts.append(page[at : m.start()])
        at = m.end()
        name = (m[2] or "").lower()
        if not name:
            if m[0].startswith("<![CDATA["):
                parts.append(html.escape(m[0][9:-3]))
            continue
        if m[1]:  # a closing tag
            k = next((k for k in range(len(stack) - 1, -1, -1) if stack[k].name == name), -1)
            if k >= 0:
                if name not in INLINE or any(e.name not in INLINE for e in stack[k:]):
                    flush()
                del stack[k:]
            elif name in ("p", "br"):
                flush() if name == "p" else parts.append(" ")
            continue
        if name in RAW:
            if name == "title" or name not in ("head",):
                close = re.compile(rf"</{re.escape(name)}\s*>", re.I).search(page, at)
                if not m[0].endswith("/>"):
                    at = close.end() if close else (end if name in ("script", "style", "textarea", "title") else at)
            if name not in INLINE:
                flush()
            continue
        if name == "br":
            parts.append(" ")
            continue
        if name not in INLINE:
            flush()
            inline_top = len(stack)
            while inline_top and stack[inline_top - 1].name in INLINE:
                inline_top -= 1
            if inline_top and name in CLOSED_BY.get(stack[inline_top - 1].name, ()):
                del stack[inline_top - 1 :]
        if name in VOID:
            continue
        up = stack[-1] if stack else Element("", False, False)
        inside = up.inside or name in ("article", "main")
        other = up.other or name not in ("html", "body", "article", "main") and (name in ASIDE and not (name == "header" and up.inside) or name not in HEADINGS and named_other(m[3] or "", up.inside))
        if name == "article" and any(NO_ARTICLE.search(a[2] or a[3] or a[4] or "") for a in ATTRIBUTE.finditer(m[3] or "") if a[1].lower() in ("class", "id")):
            other = True
        if other and not up.other and name in INLINE:
            flush()
        if not m[0].endswith("/>"):
            stack.append(Element(name, other, inside))
    flush()
    return out


# --- union-free expressions -------------------------------------------------------------------
# A node is ("text", string), ("slot",), ("tag", path), ("opt", nodes) or ("rep", nodes).


def folded(nodes: list[tuple]) -> list[tuple]:
    """Neighbouring groups that agree but for their texts become one repeated group, shortest first."""
    shape = lambda n: ("slot",) if n[0] in ("text", "slot") else n
    for width in range(2, 9, 2):
        out, k = [], 0
        while k < len(nodes):
            group, e = [shape(n) for n in nodes[k : k + width]], k + width
            while len(group) == width and [shape(n) for n in nodes[e : e + width]] == group:
                e += width
            if e > k + width:
                out.append(("rep", tuple(group)))
                k = e
            else:
                out.append(nodes[k])
                k += 1
        nodes = out
    return nodes


def stream(found: list[Block]) -> list[tuple]:
    return folded([n for b in found for n in (("tag", b.path), ("text", b.text))])


def aligned(one: list[tuple], two: list[tuple]) -> list[tuple]:
    """The least union-free expression this alignment finds for both."""
    key = lambda n: ("slot",) if n[0] in ("text", "slot") else ("rep", n[1]) if n[0] == "rep" else n
    bare = lambda n: n[1][0] if n[0] == "opt" and len(n[1]) == 1 else n
    a, b = [key(bare(n)) for n in one], [key(bare(n)) for n in two]
    out: list[tuple] = []
    optional = lambda nodes: [n if n[0] == "opt" else ("opt", (n,)) for n in nodes]
    for op, i, j, k, m in difflib.SequenceMatcher(None, a, b, autojunk=False).get_opcodes():
        if op != "equal":
            out += optional(one[i:j]) + optional(two[k:m])
            continue
        for x, y in zip(one[i:j], two[k:m]):
            n = bare(x) if bare(x) == bare(y) else ("slot",) if bare(x)[0] in ("text", "slot") else bare(x)
            out.append(("opt", (n,)) if "opt" in (x[0], y[0]) else n)
    return out


@dataclass
class Merged:
    """Pages of one sequence of groups: the paths, the texts that every page has in each, whether a group is optional, the first hashes of different pages."""

    paths: list[str]
    texts: list[list[str]]
    optional: list[bool]
    seen: list[int]

    def saw(self, other: Merged) -> None:
        self.seen = sorted({*self.seen, *other.seen})[:LEAST_PAGES]


def agreed(one: list[str], two: list[str]) -> list[str]:
    return one if one == two else [t for t in one if t in set(two)]


def merged(found: list[Block]) -> Merged:
    """A page: neighbouring groups of the same paths are one, with the texts of all of them."""
    nodes = [(b.path, [b.text]) for b in found]
    for width in range(1, 5):
        out: list[tuple[str, list[str]]] = []
        for n in nodes:
            out.append(n)
            if len(out) >= 2 * width and all(out[-k][0] == out[-k - width][0] for k in range(1, width + 1)):
                for k in range(width, 0, -1):
                    out[-k - width][1].extend(out[-k][1])
                del out[-width:]
        nodes = out
    main = "\n".join(b.text for b in found if b.inside or not b.other)
    return Merged([p for p, _ in nodes], [t for _, t in nodes], [False] * len(nodes), [int.from_bytes(hashlib.blake2b(main.encode(errors="surrogatepass"), digest_size=7).digest(), "big")])


def both(one: Merged, two: Merged) -> Merged:
    """The wrapper of the pages of both."""
    if one.paths == two.paths:
        out = Merged(one.paths, [agreed(x, y) for x, y in zip(one.texts, two.texts)], [x or y for x, y in zip(one.optional, two.optional)], one.seen)
    else:
        out = Merged([], [], [], one.seen)
        for op, i, j, k, m in difflib.SequenceMatcher(None, one.paths, two.paths, autojunk=False).get_opcodes():
            if op == "equal":
                out.paths += one.paths[i:j]
                out.texts += [agreed(x, y) for x, y in zip(one.texts[i:j], two.texts[k:m])]
                out.optional += [x or y for x, y in zip(one.optional[i:j], two.optional[k:m])]
            else:
                for part, f, t in ((one, i, j), (two, k, m)):
                    out.paths += part.paths[f:t]
                    out.texts += part.texts[f:t]
                    out.optional += [True] * (t - f)
    out.saw(two)
    return out


def likeness(one: list[str], two: list[str]) -> float:
    return difflib.SequenceMatcher(None, one, two, autojunk=False).ratio()


def templates(parts: list[Merged]) -> list[tuple[list[str], set[tuple[str, str]]]]:
    """(paths, fixed texts) of each template of a host."""
    found: list[tuple[list[str], Merged]] = []
    for m in sorted(parts, key=lambda m: (-len(m.seen), len(m.paths), m.paths)):
        score, k = max(((likeness(lead, m.paths), -k) for k, (lead, _) in enumerate(found)), default=(0.0, 0))
        if score >= 0.5:
            found[-k] = (found[-k][0], both(found[-k][1], m))
        else:
            found.append((m.paths, m))
    fixed = lambda m: {(p, t) for p, texts, o in zip(m.paths, m.texts, m.optional) if not o for t in texts} if len(m.seen) >= LEAST_PAGES else set()
    return [(lead, fixed(m)) for lead, m in found]


def chosen(paths: list[str], wrappers: list[tuple[list[str], set[tuple[str, str]]]]) -> set[tuple[str, str]]:
    """The fixed texts of the template a page is most like."""
    score, k = max(((likeness(lead, paths), -k) for k, (lead, _) in enumerate(wrappers)), default=(0.0, 0))
    return wrappers[-k][1] if score >= 0.5 else set()


def main_text(page: str | None, wrappers: list[tuple[list[str], set[tuple[str, str]]]] = ()) -> str:
    found = blocks(page or "")
    fixed = chosen(merged(found).paths, wrappers) if any(f for _, f in wrappers) else set()
    size = lambda part: sum(len(b.text) for b in part)
    held = [b for b in found if b.inside and not b.other]
    free = [b for b in found if not b.inside and not b.other and (b.path, b.text) not in fixed]
    if held:
        left = [b for b in held if (b.path, b.text) not in fixed or HEADINGS.intersection(b.path.split("/"))]
        held = left if 2 * size(left) >= size(held) else held
    # an article element with less than half of what stands outside is a teaser
    held = held if 2 * size(held) >= size(free) else free
    return "\n".join(b.text for b in held)


def host(url=None):
    return F.coalesce(F.lower(F.regexp_extract(F.col("url"), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1)), F.lit(""))


def wrappers(pages: DataFrame) -> DataFrame:
    """(host, templates): the wrappers of each host that has fixed texts, from all its pages."""
    kinds = "host string, shape string, texts array<array<string>>, seen array<long>"

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state: dict[tuple[str, str], Merged] = {}

        def told() -> pa.RecordBatch:
            cols = [[h for h, _ in state], [p for _, p in state], [m.texts for m in state.values()], [m.seen for m in state.values()]]
            types = [pa.string(), pa.string(), pa.list_(pa.list_(pa.string())), pa.list_(pa.int64())]
            out = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], names=["host", "shape", "texts", "seen"])
            state.clear()
            return out

        for b in batches:
            for name, *rest in zip(*[c.to_pylist() for c in b.columns]):
                if len(rest) == 1:
                    m = merged(blocks(rest[0]))
                else:
                    m = Merged(rest[0].split("\n"), rest[1], [False] * len(rest[1]), rest[2])
                if m.paths:
                    key = name, "\n".join(m.paths)
                    state[key] = both(state[key], m) if key in state else m
                    if len(state) >= HELD:
                        yield told()
        if state:
            yield told()

    # merged where they are read, then by host and groups
    parts = pages.where("html IS NOT NULL").select(host().alias("host"), "html").mapInArrow(learn, kinds)

    def meet(rows: pa.Table) -> pa.Table:
        return pa.Table.from_batches(learn(rows.to_batches()))

    parts = parts.groupBy("host", "shape").applyInArrow(meet, kinds)

    def infer(rows: pa.Table) -> pa.Table:
        name = rows.column("host")[0].as_py()
        found = templates([Merged(s.split("\n"), t, [False] * len(t), n) for s, t, n in zip(*[rows.column(c).to_pylist() for c in ("shape", "texts", "seen")])])
        kind = pa.list_(pa.struct([("paths", pa.list_(pa.string())), ("fixed", pa.list_(pa.struct([("path", pa.string()), ("text", pa.string())])))]))
        told = [[{"paths": p, "fixed": [{"path": x, "text": t} for x, t in sorted(f)]} for p, f in found]] if any(f for _, f in found) else []
        return pa.Table.from_arrays([pa.array([name] * len(told), pa.string()), pa.array(told, kind)], names=["_host", "templates"])

    return parts.groupBy("host").applyInArrow(infer, "_host string, templates array<struct<paths:array<string>,fixed:array<struct<path:string,text:string>>>>")


def extracted(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of each page."""
    ship(pages.sparkSession)
    known = staged(wrappers(pages))
    known = F.broadcast(known) if known.count() <= BROADCAST_HOSTS else known
    rows = pages.select("page_id", "url", "html").join(known, host() == F.col("_host"), "left").select("page_id", "url", "html", "templates")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = []
            for page, found in zip(b.column(2), b.column(3)):
                texts.append(main_text(page.as_py(), [(w["paths"], {(x["path"], x["text"]) for x in w["fixed"]}) for w in found.as_py() or ()]))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return rows.mapInArrow(read, "page_id long, url string, text string, n_chars long")


def op2_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extracted(table(spark, sf_dir, "pages"))


ORACLE = None
