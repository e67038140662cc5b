"""Main text of HTML pages by tag-path ratios."""

from __future__ import annotations

import html
import math
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column_stretches, small_batches, tidy

# fixed values: element names of the HTML standard
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
RAW = frozenset("script style noscript template iframe noembed noframes xmp svg math title textarea".split())
CLOSES_P = BLOCK - {"body", "html", "option"}
# elements and names of page furniture
FURNITURE = frozenset("nav footer aside form head button select menu dialog object audio video canvas".split())
ROLES = frozenset("navigation banner contentinfo complementary search alert alertdialog dialog form menu menubar".split())
NAMES = re.compile(r"^(ads?|advert\w*|adbox|adsense|banner\w*|sponsor\w*|promo\w*|sidebar\w*|side|menu\w*|nav\w*|breadcrumbs?|footer|foot|header|masthead|topbar|cookies?|consent|gdpr|notices?|alerts?|popup\w*|modal|overlay|newsletter|subscri\w*|signup|login|share|sharing|social|related|recommend\w*|teaser\w*|widget\w*|comments?|commentlist|disqus\w*|replies|respond|responses)$", re.I)
# an opening or closing tag up to its end, a quoted value being one unit; without the quotes' ends, up to the next ">"
TAG = re.compile(r"""<!--(?s:.*?)(?:-->|\Z)|<[!?][^>]*+>|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)>""")
BROKEN = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)>")
ATTRIBUTE = re.compile(r"""([^\s=/"'>]++)(?:\s*+=\s*+("[^"]*+"|'[^']*+'|[^\s>]++))?""")
PUNCTUATION = re.compile(r"[.,;:!?。，、]")
#: Share of the text-weighted mean weight of a page's paths that a path must reach.
THRESHOLD = 0.2
#: Scopes in which an element closes an earlier one of its kind.
ITEMS = frozenset("li dd dt tr td th option".split())
SCOPES = frozenset("ul ol dl table select".split())


class Element:
    """An open element: its tag path's number, whether it is page furniture or inside it, and whether it lies in an article or main element."""

    __slots__ = ("name", "path", "furniture", "named")

    def __init__(self, name: str, parent: "Element | None", attributes: str, path: int):
        self.name, self.path = name, path
        inside = bool(parent and parent.named)
        self.named = inside or name in ("article", "main")
        self.furniture = bool(parent and parent.furniture) or name in FURNITURE or (name == "header" and not inside)
        if not self.furniture and attributes.strip():
            got = {k.lower(): (v or "").strip("\"'") for k, v in ATTRIBUTE.findall(attributes)}
            words = f"{got.get('class', '')} {got.get('id', '')}".split()
            self.furniture = "hidden" in got or got.get("role", "").lower() in ROLES or (name not in ("html", "body", "article", "main") and any(NAMES.match(w) or NAMES.match(re.split("[-_]", w)[0]) for w in words)) or (name == "article" and any(re.match("comment", w, re.I) for w in words))


class Page:
    """Text blocks in page order, each with the number of its tag path; ``above`` gives the path that a path continues, ``section`` its outermost article or main element (0: none).

    Reading is linear in the page: paths are numbered, not spelled out, and open elements are counted by name.
    Raw elements, comments and declarations give no text. Furniture is a path of its own: the same tags inside and outside of it are told apart.
    """

    def __init__(self, page: str):
        self.blocks: list[tuple[str, int]] = []
        self.above, self.furniture, self.section, self.heading, self.numbers = [-1], [False], [0], [False], {}
        self._read(page)

    def _path(self, above: int, name: str, furniture: bool) -> int:
        key = (above, name, furniture)
        found = self.numbers.get(key)
        if found is None:
            found = self.numbers[key] = len(self.above)
            self.above.append(above)
            self.furniture.append(furniture)
            self.heading.append(name in HEADINGS)
            self.section.append(self.section[above] or (found if name in ("article", "main") else 0))
        return found

    def _read(self, page: str) -> None:
        stack = [Element("#", None, "", 0)]
        open_: dict[str, int] = {}
        block_at, scope_at = [0], [0]  # places in the stack of block elements, and of list and table elements
        parts, owner, at = [], 0, 0
        last = page.rfind(">")

        def flush():
            nonlocal parts
            if parts:
                text = " ".join(html.unescape("".join(parts)).split())
                if text:
                    self.blocks.append((text, owner))
            parts = []

        def cut(i):
            for e in stack[i:]:
                open_[e.name] -= 1
            del stack[i:]
            while block_at[-1] >= i:
                block_at.pop()
            while scope_at[-1] >= i:
                scope_at.pop()

        def close(name):
            if open_.get(name):
                i = len(stack) - 1
                while stack[i].name != name:
                    i -= 1
                cut(i)

        def say(text):
            nonlocal owner
            if text.strip() and not any(x.strip() for x in parts):
                owner = stack[-1].path
            parts.append(text)

        while at < len(page):
            start = page.find("<", at)
            if start < 0 or start > last and not page.startswith("<!--", start):
                say(page[at:])
                break
            m = TAG.match(page, start) or BROKEN.match(page, start)
            if m is None:
                say(page[at:start + 1])
                at = start + 1
                continue
            if start > at:
                say(page[at:start])
            at = m.end()
            name = (m[2] or "").lower()
            if not name:
                continue
            if name == "br":
                parts.append(" ")
                continue
            if name in BLOCK:
                flush()
            if m[1]:
                close(name)
                continue
            if name in RAW:
                end = RAW_END[name].search(page, at)
                stop = page.find(">", end.end()) if end else -1
                at = stop + 1 if stop >= 0 else len(page)
                parts.append(" " if name != "title" else "")
                continue
            if name in VOID or m[3].rstrip().endswith("/") and name not in BLOCK:
                continue
            if name in CLOSES_P and open_.get("p") and stack[block_at[-1]].name == "p":
                cut(block_at[-1])
            if name in ITEMS:
                for i in reversed(scope_at):
                    other = stack[i].name
                    if other in SCOPES or i == 0:
                        break
                    if other == name or {other, name} == {"dd", "dt"}:
                        cut(i)
                        break
            top = stack[-1]
            e = Element(name, top, m[3] or "", 0)
            e.path = self._path(top.path, name, e.furniture)
            open_[name] = open_.get(name, 0) + 1
            if name in BLOCK:
                block_at.append(len(stack))
            if name in ITEMS or name in SCOPES:
                scope_at.append(len(stack))
            stack.append(e)
        flush()


RAW_END = {name: re.compile(rf"</{name}\b", re.I) for name in RAW}


def path_weights(page: Page) -> dict[int, float]:
    """Fused weight of every path with text: the root of characters a block times punctuation marks a block, both smoothed.

    Each element of a path gets the characters, marks and blocks of everything under it. A path's own ratios are smoothed with those of the
    section that it stands in, so that a heading or a short item takes after its section, and a lone sentence in
    a list of links after that list: the outermost ``article`` or ``main`` element of the path counts half, else the element above: half for a heading, a tenth for others.
    Paths of furniture weigh nothing.
    """
    n = len(page.above)
    own = [[0, 0, 0] for _ in range(n)]
    for text, path in page.blocks:
        if not page.furniture[path]:
            x = own[path]
            x[0] += len(text)
            x[1] += len(PUNCTUATION.findall(text))
            x[2] += 1
    under = [list(x) for x in own]
    for path in range(n - 1, 0, -1):  # a path is numbered after the one it continues
        up = under[page.above[path]]
        for i in range(3):
            up[i] += under[path][i]
    out = {}
    for path in range(n):
        length, marks, blocks = own[path]
        if blocks:
            named = page.section[path]
            near = under[named or max(0, page.above[path])]
            share = 0.5 if named or page.heading[path] else 0.1
            length, marks = ((1 - share) * x / blocks + share * y / near[2] for x, y in ((length, near[0]), (marks, near[1])))
            out[path] = math.sqrt(length * (1 + marks))
    return out


def content_paths(page: Page) -> set[int]:
    """Paths whose weight reaches the threshold: a share of the mean over the page, weighted by text."""
    weights = path_weights(page)
    length = {path: 0 for path in weights}
    for text, path in page.blocks:
        if path in length:
            length[path] += len(text)
    total = sum(length.values())
    if not total:
        return set()
    least = THRESHOLD * sum(w * length[path] for path, w in weights.items()) / total
    return {path for path, w in weights.items() if w >= least}


def main_text(page: str | None) -> str:
    """Blocks of the content paths, joined by newlines."""
    read = Page(page or "")
    chosen = content_paths(read)
    return "\n".join(t for t, path in read.blocks if path in chosen)


def _extract(batches):
    for batch in batches:
        texts = [main_text(p) for _, part in column_stretches(batch.column("page")) for p in part]
        keep = [n for n in batch.schema.names if n != "page"]
        yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in keep), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [*keep, "text", "n_chars"])


def extract_text(pages: DataFrame, html_col: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """``keep`` columns, text and n_chars (code points) of every page.

    A page is one row of work; nothing is grouped. Null and empty pages, and those of
    furniture alone, have an empty text. Repeated rows are all returned; other columns are ignored.
    """
    small_batches(pages.sparkSession)
    kind = {f.name: f.dataType.simpleString() for f in pages.schema}
    rows = pages.select(*[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)], F.col(html_col).cast("string").alias("page"))
    out = rows.mapInArrow(tidy(_extract), "".join(f"k{i} {kind[c]}, " for i, c in enumerate(keep)) + "text string, n_chars long")
    return out.select(*[F.col(f"k{i}").alias(c) for i, c in enumerate(keep)], "text", "n_chars")
