"""HTML extraction by maximum-scoring subsequence.

A page is a sequence of words and tags. A word scores by the container it stands in, a tag negative. Containers are told by
their element and by the tokens of their class, id and role names; each token has a weight, log odds of standing in
the main part, learnt from labelled pages: those that mark it by an ``article`` or ``main`` element, whatever names they give. Word lists are
no more than the weights of tokens that were seen too rarely. One linear scan finds the contiguous
region of the highest sum; its text, less what stands in boilerplate inside it, is the page's main text.
"""

from __future__ import annotations

import html as _html
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most labelled pages that weights are learnt from: those of smallest id hash.
LABELLED = 2_000
#: Times that a feature must be seen before its learnt weight counts in full.
PRIOR = 20.0
#: Elements of HTML that break a line, that hold no text to read, and that never hold main text.
BLOCK = frozenset("address article aside blockquote body br button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html iframe legend li main menu nav noscript ol optgroup option p pre section select summary table tbody td template textarea tfoot th thead title tr ul video audio canvas object".split())
RAW = ("script", "style", "noscript", "template", "textarea", "iframe", "title", "svg", "select", "object", "canvas")
OUTSIDE = frozenset("nav footer aside form button menu dialog fieldset select option label input".split())
CONTAINERS = frozenset("article main nav aside header footer form div section ul ol dl table figure button menu dialog fieldset blockquote details label".split())
#: Words in class, id and role names that speak against the main part, for it, and of a part's own head.
NOT_MAIN = frozenset("ad ads advert adverts advertisement advertising banner banners sponsor sponsors sponsored promo promos promotion cookie cookies consent notice alert popup modal overlay sidebar side widget widgets menu menus nav navbar navigation navi breadcrumb breadcrumbs footer masthead comment comments commentlist reply replies discussion disqus respond share sharing social related recommend recommended recommendations newsletter subscribe subscription signup login search pagination pager tags copyright legal disclaimer toolbar complementary contentinfo".split())
MAIN = frozenset("article main content post entry story body text".split())
HEAD = frozenset(("header", "byline"))

_ATTRIBUTES = r"""(?:[^>"']|"[^"]{0,65536}"|'[^']{0,65536}')*"""
_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)"
    rf"|<(script|style)\b{_ATTRIBUTES}>.*?(?:</\1\s*>|\Z)"  # without an end they run to the page's end
    rf"|<({'|'.join(RAW[2:])})\b{_ATTRIBUTES}(?<!/)>.*?</\2\s*>"
    rf"|<(/?)([a-zA-Z][^\s/>]*)({_ATTRIBUTES})>"
    r"|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)"  # a quote that never ends
    r"|<[!?/][^>]*(?:>|\Z)",
    re.S | re.I,
)
_NAMED = re.compile(r"""(?:^|\s)(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|$)|aria-hidden\s*=\s*[\"']?true|display\s*:\s*none", re.I)
_PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])")
#: Log odds at which a token decides for itself.
DECIDES = 0.5


def tokens_of(attributes: str) -> list[str]:
    """The tokens of a tag's class, id and role names."""
    if "=" not in attributes:
        return []
    return [t for m in _NAMED.finditer(attributes) for x in m.groups() if x for t in x.split()]


def token_default(token: str) -> float:
    """The weight of a name that was never seen: by the word lists, none for most names; +2 where all its words speak for the main part."""
    parts = [x.lower() for x in _PARTS.findall(token)]
    if any(x in NOT_MAIN for x in parts):
        return -2.0
    if any(x in HEAD for x in parts):
        return -1.0
    if any(x in MAIN for x in parts):
        return 2.0 if len(parts) > 1 and all(x in MAIN for x in parts) else 1.0
    return 0.0


def _kind(tag: str, attributes: str, inside: str, weights: dict[str, float]) -> str:
    """The container's feature: its element, marked with - where it is boilerplate (-~ inside a main part) and + where a main part.

    Elements that never hold main text decide first, then the names' weights: one that is sure of the main part beats one that isn't, else the least weight counts.
    """
    main = inside.startswith("+")
    if inside.startswith("-") and tag not in ("article", "main") or inside.startswith("-~"):
        return inside
    against = f"-~{tag}" if main else f"-{tag}"
    if tag in OUTSIDE or tag == "header" and not main or attributes and _HIDDEN.search(attributes):
        return against
    if tag in ("article", "main"):
        return f"+{tag}"
    names = tokens_of(attributes)
    if names:
        # the head of a main part belongs to it
        said = [w for t, w in ((t, weights.get(f".{t}", token_default(t))) for t in names) if not (main and w == -1.0 and f".{t}" not in weights)]
        if said and max(said) < 2.0 and min(said) <= -DECIDES:
            return against
        if said and max(said) >= DECIDES:
            return f"+{tag}"
    return inside if main else tag


def parse(page: str, weights: dict[str, float] | None = None) -> list[tuple[str, str | None, bool]]:
    """(feature, text or null, whether it breaks a block) in page order; tags have null text."""
    return [x[:3] for x in _parse(page, weights or {}, False)]


def _parse(page: str, weights: dict[str, float], trace: bool) -> list[tuple[str, str | None, bool, tuple[str, ...]]]:
    """``parse``, with the elements and names around each word where they are asked for."""
    out: list[tuple[str, str | None, bool, tuple[str, ...]]] = []
    stack: list[tuple[str, str, tuple[str, ...]]] = []
    at, where, around = 0, "body", ()
    for m in _TOKEN.finditer(page):
        if m.start() > at:
            out.append((where, page[at : m.start()], False, around))
        at = m.end()
        raw = m.group(1) or m.group(2)
        closing, tag, attributes = (m.group(3), m.group(4), m.group(5)) if m.group(4) else (m.group(6), m.group(7), m.group(8))
        tag = (tag or "").lower()
        if not tag:
            if raw and raw.lower() in BLOCK:
                out.append((f"<{raw.lower()}", None, True, around))
            continue
        place = where
        if tag in CONTAINERS:
            if not closing:
                if not attributes.endswith("/"):
                    stack.append((tag, where, around))
                    where = _kind(tag, attributes, where, weights)
                    if trace:
                        around = (*around, tag, *("." + t for t in tokens_of(attributes)))
            else:
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i][0] == tag:
                        _, where, around = stack[i]
                        del stack[i:]
                        break
        place = place if closing else where
        out.append((f"<{'+' if place.startswith(('+', '-~')) else '-' if place[0] == '-' else ''}{closing}{tag}", None, tag in BLOCK, around))
    if at < len(page):
        out.append((where, page[at:], False, around))
    return out


def labels(page: str) -> list[tuple[str, str | None, tuple[str, ...], bool | None]] | None:
    """For a page with an ``article`` or ``main`` element, each token's feature, text, surroundings, and whether it lies in that element.

    The label is the element's alone, whatever names are given; words whose container the lists hold to be boilerplate inside a main
    part tell nothing and have none. Null for other pages.
    """
    tokens, out, marked, inside = _parse(page, {}, True), [], False, False
    for feature, text, _, around in tokens:
        if text is not None and text.strip():
            inside = "article" in around or "main" in around
            marked = marked or inside
        out.append((feature, text, around, None if inside and feature.startswith("-") else inside))
    return out if marked else None


#: Weight of a word of boilerplate that stands inside a main part: it is left out in any case, and shall not end the region.
NESTED = -0.1


def default_weight(feature: str) -> float:
    """The weight before any page is seen."""
    if feature[0] == ".":
        return token_default(feature[1:])
    if feature[0] == "<":
        return {"+": -0.05, "-": -0.5}.get(feature[1:2], -0.3)
    if feature.startswith("-~"):
        return NESTED
    return {"-": -2.0, "+": 1.0}.get(feature[0], 0.5)


def weight(feature: str, main: float, other: float) -> float:
    """Log odds of the main part, drawn to the default while rarely seen. Names keep the sign that their counts give; tags stay below 0 and plain containers above it."""
    if feature.startswith(("-~", "<+")):
        return default_weight(feature)
    odds = max(-2.0, min(1.0, math.log((main + 1) / (other + 1))))
    n = main + other
    mixed = (n * odds + PRIOR * default_weight(feature)) / (n + PRIOR)
    if feature[0] == "<":
        return max(-0.5, min(-0.05, mixed))
    return mixed if feature[0] in ".+" else min(-0.05, mixed) if feature[0] == "-" else max(0.2, mixed)


def learn(pages: DataFrame, limit: int = LABELLED) -> dict[str, float]:
    """Weights from at most ``limit`` pages that mark their main part; features and their counts come to the driver.

    Null pages and ids aren't taken; without a marked page there are no weights, and defaults hold.
    """
    marked = pages.where(F.col("html").rlike("(?i)<(article|main)[\\s>]")).select("page_id").where("page_id is not null")
    ids = [r[0] for r in marked.distinct().orderBy(F.xxhash64("page_id"), "page_id").limit(limit).collect()]
    if not ids:
        return {}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, list[int]] = {}
        for b in batches:
            for page in b.column(0).to_pylist():
                for feature, text, around, inside in labels(page or "") or ():
                    n = 1 if text is None else len(text.split())
                    if inside is None or not n:
                        continue
                    for f in {feature, *(x for x in around if x[0] == "." and text is not None)}:
                        seen.setdefault(f, [0, 0])[0 if inside else 1] += n
        if seen:
            yield pa.RecordBatch.from_arrays([pa.array(list(seen)), pa.array([x[0] for x in seen.values()]), pa.array([x[1] for x in seen.values()])], ["feature", "main", "other"])

    counts = pages.where(F.col("page_id").isin(ids)).select("html").mapInArrow(run, "feature string, main bigint, other bigint")
    return {f: weight(f, m, o) for f, m, o in counts.groupBy("feature").agg(F.sum("main"), F.sum("other")).collect()}


def region(values: list[float]) -> tuple[int, int]:
    """Bounds of the contiguous stretch of the highest sum, the first of equals; empty where none is above 0."""
    best, bounds, total, start = 0.0, (0, 0), 0.0, 0
    for i, v in enumerate(values):
        if total <= 0:
            total, start = 0.0, i
        total += v
        if total > best:
            best, bounds = total, (start, i + 1)
    return bounds


def extract(page: str | None, weights: dict[str, float]) -> str:
    """The main text: one line for each block, character references decoded, white space made single."""
    tokens = parse(page or "", weights)
    of = {f: weights.get(f, default_weight(f)) for f in {t[0] for t in tokens}}
    a, b = region([of[f] if text is None else of[f] * len(text.split()) for f, text, _ in tokens])
    blocks, part = [], []
    for feature, text, breaks in tokens[a:b]:
        if breaks:
            blocks.append(part)
            part = []
        elif text is not None and of[feature] > 0:
            part.append(_html.unescape(text))
    lines = (" ".join("".join(x).split()) for x in [*blocks, part])
    return "\n".join(x for x in lines if x)


def main_text(pages: DataFrame, weights: dict[str, float]) -> DataFrame:
    """``page_id``, ``url``, ``text`` and ``n_chars`` of every row.

    Null and empty pages, and pages without a region above 0, give empty text; a page is parsed whole, whatever its length, in time linear in
    it. Repeated rows are answered each, an empty table gives an empty one, and other columns are left behind, whatever their names.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [extract(x, weights) for x in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    pages = pages.select("page_id", "url", "html")
    return pages.mapInArrow(run, f"page_id {pages.schema[0].dataType.simpleString()}, url string, text string, n_chars bigint")
