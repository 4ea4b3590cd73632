"""Main text of HTML pages by tag-path ratios."""

from __future__ import annotations

import html as entities
import math
import re
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import free_name

# Element kinds of HTML.
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
RAW = set("script style noscript template textarea iframe noembed noframes xmp svg math canvas".split())
INLINE = set(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span "
    "strike strong sub sup time tt u var wbr br img picture".split()
)
HEADINGS = {"h1", "h2", "h3", "h4", "h5", "h6"}
BOILERPLATE = set(
    "head nav footer aside form button select option datalist dialog menu object audio video map fieldset".split()
)
BOILER_ROLES = set("navigation banner contentinfo complementary search form alert alertdialog dialog menu menubar toolbar note".split())
ENDS_P = set(
    "address article aside blockquote center details dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "header hr main menu nav ol p pre section table ul".split()
)
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPE = {"ul", "ol", "dl", "table", "article", "section", "div", "body", "main", "menu"}
# Words in class or id that mark what is not the article.
HINTS = re.compile(
    r"(?<![a-z])(?:ads?|advert\w*|adsense|adslot|sponsor\w*|promo\w*|banner|cookie\w*|consent|gdpr|notice|notification|popup|modal|overlay|"
    r"newsletter|subscri\w+|signup|side-?bar|sidenav|nav|navbar|navigation|menu|breadcrumbs?|site-?header|page-?header|masthead|topbar|"
    r"footer|comments?|comment-?list|disqus|replies|reply|respond|share|sharing|social|related|recommended|recommendations|pagination|"
    r"pager|login|widget|toolbar|skip-?link|copyright|hidden|sr-only|visually-hidden)(?![a-z])"
)
# First parts of a class that tell of an element's state, not of what it is.
STATES = set("has with no without is not show hide js wide enable enabled disable disabled".split())
CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")
PARTS = re.compile(r"[-_:]+")
TOKEN = re.compile(
    r"<(?:!--(?:>|->|.*?(?:--!?>|\Z))|(?P<decl>[!?])[^>]*(?:>|\Z)|"
    r"(?P<end>/?)(?P<name>[A-Za-z][^\s/>]*)(?P<attrs>(?>[^>\"']+|\"[^\"]*\"|'[^']*')*+)[^>]*(?:>|\Z))",
    re.S,
)
ATTR = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.S)
PUNCTUATION = re.compile(r"[.,;:!?…、。，！？]")


@dataclass
class Block:
    """Text of one block element; consecutive text with inline markup is one block."""

    path: tuple[str, ...]
    tag: str
    boiler: bool
    region: int  # number of the innermost article or main element around it, or 0
    hints: tuple[int, ...] = ()  # numbers of the elements around it whose class or id is a hint
    parts: list[str] = field(default_factory=list)
    linked: int = 0
    text: str = ""


def _flags(name: str, raw: str) -> tuple[str, bool, bool]:
    """(first class, whether the element is hidden or has another role, whether class or id hint at it)."""
    if not raw or raw.isspace():
        return "", False, False
    got = {}
    for m in ATTR.finditer(raw):
        got.setdefault(m[1].lower(), m[2] or m[3] or m[4] or "")
    names = [CAMEL.sub("-", x).lower() for k in ("class", "id") for x in got.get(k, "").split()]
    hinted = name not in ("html", "body") and any(HINTS.search(x) and PARTS.split(x)[0] not in STATES for x in names)
    style = got.get("style", "").replace(" ", "").lower()
    hidden = "hidden" in got or got.get("aria-hidden") == "true" or "display:none" in style or "visibility:hidden" in style
    first = got.get("class", "").split()
    return (first[0] if first else ""), hidden or got.get("role", "").lower() in BOILER_ROLES, hinted


def blocks(page: str) -> list[Block]:
    """Text blocks of a page in order.  Any text is taken; nothing is an error.

    What an element's kind, role or style says of it holds for all that is in
    it.  A class or id is only a hint: where the element has all of the other
    text, or most of it with a first heading, an article or a main element,
    the hint says nothing.
    """
    # name, path step, not the article, in an article, region, hints
    stack: list[tuple[str, str, bool, bool, int, tuple[int, ...]]] = []
    chief: list[bool] = [False]  # by hint: whether the element has a first heading, an article or a main element
    out: list[Block] = []
    current: Block | None = None
    links = regions = 0
    pos, size = 0, len(page)

    def add(text: str) -> None:
        nonlocal current
        if not text:
            return
        if current is None:
            if text.isspace():
                return
            outer = [s for s in stack if s[0] not in INLINE]
            boiler = any(s[2] for s in stack)
            region, hints = stack[-1][4:] if stack else (0, ())
            current = Block(tuple(s[1] for s in outer), outer[-1][0] if outer else "", boiler, region, hints)
            out.append(current)
        if any(s[2] for s in stack[-3:] if s[0] in INLINE) and not current.boiler:
            return  # a marked inline element inside a block
        current.parts.append(text)
        if links:
            current.linked += len(text)

    def close(upto: int) -> None:
        nonlocal current, links
        for name, *_ in stack[upto:]:
            if name == "a":
                links = max(0, links - 1)
            elif name not in INLINE:
                current = None
        del stack[upto:]

    while pos < size:
        at = page.find("<", pos)
        if at < 0:
            add(page[pos:])
            break
        if at > pos:
            add(page[pos:at])
        m = TOKEN.match(page, at)
        if m is None:
            add("<")
            pos = at + 1
            continue
        pos = m.end()
        name = m["name"]
        if name is None:
            continue
        name = name.lower()
        if m["end"]:
            if name == "br":
                add(" ")
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == name:
                    close(k)
                    break
            else:
                if name == "p":
                    current = None
            continue
        if name in ENDS_P:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == "p":
                    close(k)
                    break
                if stack[k][0] not in INLINE:
                    break
        if name in ENDS:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] in ENDS[name]:
                    close(k)
                    break
                if stack[k][0] in SCOPE:
                    break
        if name in VOID:
            if name in ("br", "hr", "img", "wbr"):
                if name == "hr":
                    current = None
                elif name == "br":
                    add(" ")
            continue
        closed = m[0].endswith("/>")
        if name in RAW:
            if not closed or name in ("script", "style"):
                end = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^>]*>?", re.I).search(page, pos)
                if end is None and name in ("svg", "math", "canvas", "noscript", "template", "iframe"):
                    continue
                pos = end.end() if end else size
            continue
        if closed and name not in INLINE and name not in ENDS_P:
            continue
        first, marked, hinted = _flags(name, m["attrs"])
        inside = bool(stack) and stack[-1][3]
        hints = stack[-1][5] if stack else ()
        if name in INLINE:
            marked = marked or hinted
        elif hinted:
            hints = (*hints, len(chief))
            chief.append(False)
        if name == "header":
            marked = marked or not inside
        step = name + ("." + first if first and name not in INLINE else "")
        if name not in INLINE:
            current = None
        elif name == "a":
            links += 1
        region = stack[-1][4] if stack else 0
        if name in ("article", "main", "h1") and not marked:
            for h in hints:
                chief[h] = True
            if name != "h1":
                regions += 1
                region = regions
        stack.append((name, step, marked or name in BOILERPLATE, inside or (name == "article" and not marked), region, hints))
    for b in out:
        b.text = " ".join(entities.unescape("".join(b.parts)).split())
    out = [b for b in out if b.text]
    size, total = [0] * len(chief), 0
    for b in out:
        if not b.boiler:
            total += len(b.text)
            for h in b.hints:
                size[h] += len(b.text)
    void = {h for h in range(1, len(chief)) if size[h] == total or (chief[h] and 2 * size[h] > total)}
    for b in out:
        b.boiler = b.boiler or any(h not in void for h in b.hints)
    return out


def content(found: list[Block], smoothing: float = 1.0, share: float = 0.25) -> list[Block]:
    """The blocks that are content.

    For every root-to-leaf tag path the text length, the punctuation and the
    linked text of its blocks are added up.  A path's ratio is its mean text
    length times its mean punctuation, less for linked text.  Ratios along the
    page are smoothed by a Gaussian, own and smoothed ratio are fused by their
    geometric mean, and paths whose mean fused ratio reaches a share of the
    ratios' standard deviation are content.  Headings before content are
    content.  Blocks that markup names as something else never are.

    An article or main element is one more input of the score: its blocks have
    at least the mean fused ratio of the element's text, so short paths within
    a rich article stay.  It only lifts, and takes nothing from paths outside.
    """
    found = [b for b in found if not b.boiler]
    if not found:
        return []
    length, marks, linked, count = (defaultdict(int) for _ in range(4))
    for b in found:
        length[b.path] += len(b.text)
        marks[b.path] += len(PUNCTUATION.findall(b.text))
        linked[b.path] += min(b.linked, len(b.text))
        count[b.path] += 1
    ratio = {
        p: (length[p] / n) * (1 + marks[p] / n) * (1 - linked[p] / length[p]) ** 2 for p, n in count.items()
    }
    own = [ratio[b.path] for b in found]
    reach = max(1, math.ceil(2 * smoothing))
    weight = [math.exp(-(d * d) / (2 * smoothing * smoothing)) for d in range(-reach, reach + 1)]
    fused = defaultdict(float)
    for i, b in enumerate(found):
        near = [(own[i + d], weight[d + reach]) for d in range(-reach, reach + 1) if 0 <= i + d < len(own)]
        smooth = sum(v * w for v, w in near) / sum(w for _, w in near)
        fused[b.path] += math.sqrt(own[i] * smooth) / count[b.path]
    mean = sum(own) / len(own)
    spread = math.sqrt(sum((v - mean) ** 2 for v in own) / len(own))
    least = min(share * spread if spread else 0.0, max(fused.values()))
    held, size = defaultdict(float), defaultdict(int)
    for b in found:
        if b.region:
            held[b.region] += fused[b.path] * len(b.text)
            size[b.region] += len(b.text)
    score = [max(fused[b.path], held[b.region] / size[b.region] if b.region else 0.0) for b in found]
    chosen = [v >= least and v > 0 for v in score]
    for i in range(len(found) - 2, -1, -1):
        if found[i].tag in HEADINGS and chosen[i + 1]:
            chosen[i] = True
    return [b for b, c in zip(found, chosen) if c]


def main_text(page: str | None) -> str:
    """Main text: blocks of content in page order, joined by one space."""
    return " ".join(b.text for b in content(blocks(page or "")))


def extract(pages: DataFrame, html: str = "html") -> DataFrame:
    """Every row of ``pages`` without the html, with text and n_chars.

    Null and empty pages, and pages without content, give the empty text.
    Repeated rows are extracted each.  Columns named text or n_chars are
    replaced.  One pass over the pages, no shuffle.
    """
    held = pages.drop(*[c for c in pages.columns if c.lower() in ("text", "n_chars") and c != html])
    name = html
    if html in ("text", "n_chars"):
        name = free_name(held.columns, "_html")
        held = held.withColumnRenamed(html, name)
    rest = [f for f in held.schema.fields if f.name != name]
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in rest] + ["text string", "n_chars long"])
    keep = [f.name for f in rest]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                texts = [main_text(x.as_py()) for x in part.column(name)]
                yield pa.RecordBatch.from_arrays(
                    [*(part.column(c) for c in keep), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())],
                    [*keep, "text", "n_chars"],
                )

    return held.mapInArrow(work, schema)
