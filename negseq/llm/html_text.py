"""HTML extraction by the maximum-scoring subsequence of a page's tokens.

A page is a sequence of tags and words. Words score by where they stand (the tag around
them, and whether an ``article`` or ``main`` element holds them), tags cost a little, and
a linear scan finds the contiguous region of the highest total. The weights are log-odds
of standing inside the content, learnt from labelled pages: those that mark their content
by an ``article`` or ``main`` element label themselves. The same pages
are counted without their marks too, so pages that mark nothing have weights of their own.
The region then grows to whole blocks. Subtrees that are never content (menus, forms,
scripts, adverts, comments and the like) score nothing and are left out of the text.

Defined results: null and empty html, and pages without a region of positive score, give the
empty text; malformed nesting is closed as far as the tags allow; repeated rows each
get their text; a null url stays null; extra columns are not read; a tag that never ends, and a page of any
length, are read in linear time. Character references are decoded, runs of white
space (also no-break spaces) in a block become one space, blocks are joined by a line break.
"""

from __future__ import annotations

import html
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Labelled pages to learn from at most; each adds a few dozen counts.
TRAIN_PAGES = 400

# Elements of the HTML standard by their role.
RAW = "script style template noscript textarea title iframe svg math object canvas".split()
VOID = "area base br col embed hr img input link meta source track wbr param".split()
BLOCK = "address article aside blockquote body br center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main nav ol p pre section summary table tbody td tfoot th thead tr ul".split()
NEVER = "nav footer aside form button select option dialog menu head label input".split()
# Words that name boilerplate in class, id and role.
BOILER = "ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments complementary contentinfo cookie cookies consent disqus disclaimer footer gdpr menu modal nav navbar navigation newsletter notice notices popup promo promotion promoted related recommended replies reply search share sharing sidebar social sponsor sponsored subscribe subscription toolbar widget widgets".split()

_RAW, _VOID, _BLOCK, _NEVER, _BOILER = map(frozenset, (RAW, VOID, BLOCK, NEVER, BOILER))
_OTHER = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</[^A-Za-z][^>]*(?:>|\Z)", re.S)
_NAME = re.compile(r"<(/?)([A-Za-z][^\s/>]*)")
_STOP = re.compile(r"[>\"']")
_NAMES = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_HIDDEN = re.compile(r"(?:^|\s)hidden(?=[\s=/]|$)|aria-hidden\s*=\s*[\"']?true|display\s*:\s*none", re.I)
_SPACE = re.compile(r"\s+")
#: An opening tag of the left kind closes an open one of the right kinds.
_CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
_P_ENDS = _BLOCK - {"br", "td", "th", "tr", "tbody", "thead", "tfoot", "body", "html"}


def boilerplate(tag: str, attributes: str, inside_content: bool) -> bool:
    if tag in _NEVER or (tag == "header" and not inside_content):
        return True
    if not attributes or tag in ("html", "body", "article", "main"):
        return False
    if _HIDDEN.search(attributes):
        return True
    named = " ".join(a or b or c for a, b, c in _NAMES.findall(attributes)).lower()
    return any(w in _BOILER for w in re.split(r"[^a-z]+", named))


class Tags:
    """The parts of a page: (slash, tag, attributes, text) of each tag, or of the text between. What is not a tag is text. Quotes are respected in tags as long as they close."""

    def __init__(self, page: str):
        self.page, self.last = page, {q: page.rfind(q) for q in "\"'>"}
        self.quotes = True

    def end(self, at: int) -> int:
        """Place of the ">" that ends the tag whose name ends here, or -1."""
        page, begin = self.page, at
        while self.quotes and (m := _STOP.search(page, at)) is not None:
            if m.group() == ">":
                return m.start()
            if m.start() >= self.last[m.group()]:
                # it never closes
                return page.find(">", begin)
            at = page.index(m.group(), m.end()) + 1
        if begin <= self.last[">"]:
            # every later ">" is in quotes: from here on quotes say nothing, so that no tag is searched to the end again
            self.quotes = False
            return page.find(">", begin)
        return -1

    def __iter__(self) -> Iterator[tuple[str | None, str | None, str | None, str | None]]:
        page, at, n = self.page, 0, len(self.page)
        while at < n:
            if page[at] != "<":
                stop = page.find("<", at)
                stop = n if stop < 0 else stop
                yield None, None, None, page[at:stop]
                at = stop
                continue
            if (m := _OTHER.match(page, at)) is not None:
                at = m.end()
                continue
            m = _NAME.match(page, at)
            stop = self.end(m.end()) if m is not None else -1
            if stop < 0:
                # not a tag; a tag that the page's end cuts off leaves no further one
                rest = n if m is not None else at + 1
                yield None, None, None, page[at:rest]
                at = rest
                continue
            self.at = stop + 1
            yield m.group(1), m.group(2), page[m.end() : stop], None
            at = self.at


def parse(page: str) -> list[tuple[str, str, bool, bool]]:
    """Tokens (kind, value, inside an article or main, inside boilerplate). kind: a path of tags for text, or "<" for a tag that begins or ends a block."""
    out: list[tuple[str, str, bool, bool]] = []
    stack: list[tuple[str, bool, bool]] = []
    tags = Tags(page)
    for slash, tag, attributes, text in tags:
        inside, boiler = (stack[-1][1], stack[-1][2]) if stack else (False, False)
        if text is not None:
            out.append((stack[-1][0] if stack else "", text, inside, boiler))
            continue
        tag = tag.lower()
        if slash:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    # an end tag of an inline element does not close blocks
                    if tag in _BLOCK or not any(s[0] in _BLOCK for s in stack[k + 1 :]):
                        del stack[k:]
                    break
            if tag in _BLOCK:
                out.append(("<", tag, inside, boiler))
            continue
        if tag in _RAW:
            stop = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, tags.at)
            tags.at = stop.end() if stop else len(page)
            out.append(("<", tag, inside, boiler))
            continue
        if tag in _BLOCK:
            if tag in _P_ENDS:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k][0] == "p":
                        del stack[k:]
                        break
                    if stack[k][0] in _BLOCK:
                        break
            ends = _CLOSES.get(tag, ())
            while stack and (stack[-1][0] in ends):
                stack.pop()
            inside, boiler = (stack[-1][1], stack[-1][2]) if stack else (False, False)
            out.append(("<", tag, inside, boiler))
        if tag not in _VOID and not attributes.endswith("/"):
            content = inside or tag in ("article", "main")
            stack.append((tag, content, boiler or boilerplate(tag, attributes, inside)))
    return out


def feature(path: str, inside: bool, marked: bool) -> str:
    """Where a word stands: the tag around it, and on pages that mark their content whether the mark holds it."""
    return f"{path}|{'in' if inside else 'out'}" if marked else path


class Weights:
    def __init__(self, odds: dict[str, float], tag_cost: float = 0.3):
        self.odds, self.tag_cost = odds, tag_cost

    def word(self, path: str, inside: bool, marked: bool) -> float:
        odds = self.odds
        found = odds.get(feature(path, inside, marked))
        if found is None and marked:
            # a tag that no page had there
            found = odds.get(feature("", inside, True))
        return odds.get("other", 0.2) if found is None else found


#: Weights where no labelled page is at hand.
PLAIN = Weights({"p": 2.0, "a": -1.0, "li": 0.3, "other": 0.4})


def marks(tokens: list[tuple[str, str, bool, bool]]) -> bool:
    return any(inside and not boiler and path != "<" and text.strip() for path, text, inside, boiler in tokens)


def fit(pages: list[str]) -> Weights:
    """Log-odds that a word in such surroundings is content, with add-one smoothing, from pages that mark their content: with the mark as part of the surroundings, over all tags, and without it."""
    counts: dict[str, list[int]] = {}
    for page in pages:
        tokens = parse(page or "")
        if marks(tokens):
            for path, text, inside, boiler in tokens:
                if path != "<" and not boiler and (n := len(text.split())):
                    for name in {feature(path, inside, True), feature("", inside, True), path}:
                        counts.setdefault(name, [0, 0])[inside] += n
    if not counts:
        return PLAIN
    odds = {f: max(-3.0, min(3.0, math.log((c[1] + 1) / (c[0] + 1)))) for f, c in counts.items()}
    return Weights({**PLAIN.odds, "|in": 3.0, "|out": -3.0, **odds})


def region(tokens: list[tuple[str, str, bool, bool]], weights: Weights) -> tuple[int, int]:
    """First and last token (exclusive) of the best contiguous region, grown to whole blocks; (0, 0) if none scores."""
    marked = marks(tokens)
    best, total, start, found = 0.0, 0.0, 0, (0, 0)
    for i, (path, text, inside, boiler) in enumerate(tokens):
        if boiler:
            # left out of the text, so it neither joins nor parts
            continue
        if path == "<":
            score = -weights.tag_cost
        elif n := len(text.split()):
            score = n * weights.word(path, inside, marked)
        else:
            continue
        if total <= 0:
            total, start = 0.0, i
        total += score
        if total > best:
            best, found = total, (start, i + 1)
    first, last = found
    while 0 < first and tokens[first - 1][0] != "<":
        first -= 1
    while 0 < last < len(tokens) and tokens[last][0] != "<":
        last += 1
    return first, last


def extract(page: str | None, weights: Weights) -> str:
    tokens = parse(page or "")
    first, last = region(tokens, weights)
    blocks, now = [], []
    for path, text, _, boiler in tokens[first:last]:
        if path == "<":
            blocks.append("".join(now))
            now = []
        elif not boiler:
            now.append(text)
    blocks.append("".join(now))
    clean = (_SPACE.sub(" ", html.unescape(b)).strip() for b in blocks if b)
    return "\n".join(b for b in clean if b)


def texts(weights: Weights):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [extract(x, weights) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.string()), pa.array([len(x) for x in out], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return run


def extract_text(pages: DataFrame, train_pages: int = TRAIN_PAGES, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, url, text, n_chars. Weights come from at most train_pages pages of least id hash."""
    at = F.xxhash64(id_col)
    # the hashes alone are sorted, so the driver sees no page but those of the sample
    last = pages.select(at.alias("at")).orderBy("at").limit(train_pages).agg(F.max("at")).first()[0]
    sample = [r[0] for r in pages.where(at <= F.lit(last)).select(html_col).limit(train_pages).collect()] if last is not None else []
    rows = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    kind = dict(pages.dtypes)[id_col]
    return rows.mapInArrow(texts(fit(sample)), f"page_id {kind}, url string, text string, n_chars long")
