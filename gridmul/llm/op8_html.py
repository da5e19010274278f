"""HTML extraction by minimum-cut labelling.

A page becomes a sequence of text blocks. Each block has the cost of calling it content and that of calling it boilerplate,
from a classifier: log-odds of its tags and names, which are bounded, plus those of a logistic model of its words and links,
bounded too. Neighbouring blocks, and blocks that follow each other in one element, pay for being labelled differently. All
costs are on the same scale of log-odds, so text and neighbours can overrule a tag or a name: a sound paragraph in an article
stays whatever its class, and without any telling tag the words and the neighbours decide. The cheapest labelling is a minimum
cut, found by augmenting paths; the content side is the main text. All work is within a page, so the operator is one pass
without a shuffle.

The text model is trained on a bounded sample of pages (TRAIN_PAGES), with the blocks that sectioning tags label as its
examples; tags and names are no features of it, their log-odds are parameters.

Defined cases: null or empty HTML gives an empty text; unclosed and cut-off tags are read to the end; script and style end
at their own end tag only, wherever that is; the head ends where something stands that cannot be in it; another skipped
element that is never closed ends at the first block tag in it or at the end tag around it; text outside any tag is a block;
very long pages are read whole; of two labellings that cost the same the one with less content is taken; repeated rows are treated
alike; an empty table gives an empty result and needs no model; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import html
import math
import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridmul.llm.common import map_rows, sample_rows

TRAIN_PAGES = 2000

#: Element names.
BLOCK_TAGS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead tr ul".split())
SKIPPED = frozenset("script style noscript template svg math iframe object canvas title textarea select button audio video".split())
#: Their content is text up to the end tag, whatever it looks like.
RAW_TAGS = frozenset("script style iframe textarea title".split())
HEAD_TAGS = frozenset("base basefont bgsound head html link meta noscript script style template title".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SPACE_TAGS = frozenset(["br", "img", "wbr", "td", "th"])
BOILER_TAGS = frozenset("nav footer aside form menu dialog header".split())
CONTENT_TAGS = frozenset(["article", "main"])
CLOSED_BY_SIBLING = {"p": frozenset(["p"]), "li": frozenset(["li"]), "dd": frozenset(["dd", "dt"]), "dt": frozenset(["dd", "dt"]), "tr": frozenset(["tr", "td", "th"]), "td": frozenset(["td", "th"]), "th": frozenset(["td", "th"]), "option": frozenset(["option"])}
BOILER_NAME = re.compile(r"(?i)(^|[-_ ])(ad|ads|adv|advert\w*|banner|breadcrumbs?|comments?|commentlist|cookies?|consent|disqus|footer|menu|modal|nav|navbar|navigation|newsletter|notices?|pager|pagination|popup|promo\w*|related|replies|reply|respond|share|sharing|sidebar|side|signup|skip|social|sponsor\w*|subscribe|tags|toolbar|topbar|widgets?)([-_ ]|$)")
HEAD_NAME = re.compile(r"(?i)(^|[-_ ])(header|masthead)([-_ ]|$)")
CONTENT_NAME = re.compile(r"(?i)(^|[-_ ])(article|articlebody|body|content|entry|main|page|post|story|text)([-_ ]|$)")
#: Elements that are a paragraph or a part of one, and seldom hold a section.
PARAGRAPHS = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre a b i em strong span u small".split())
BOILER_ROLE = frozenset("navigation banner contentinfo complementary search dialog alert form menu menubar".split())

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*(?:\"|\Z)|'[^']*(?:'|\Z))*)(?:>|\Z)", re.S)
ATTR = re.compile(r"([a-zA-Z-]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))")
BLANKS = re.compile(r"\s+")
END_TAG = {t: re.compile(rf"(?i)</{t}(?=[\s/>]|\Z)[^>]*(?:>|\Z)") for t in SKIPPED}

#: Log-odds of content: within an article, in an element whose name speaks for content, in one of boilerplate (by tag, role or
#: name), in a paragraph whose own name does.
ARTICLE, CONTENT, BOILER, PARAGRAPH = 4.0, 1.5, -10.5, -3.0
#: What the words and links of a block can add or take.
TEXT_BOUND = 4.0
#: Capacities between neighbours, and between blocks that follow each other in one element.
NEAR, SIBLING = 0.8, 0.4

#: log words, share of linked words, full stops a word, ends like a sentence, capitals, heading, list item, bias
START_WEIGHTS = (0.9, -4.0, 4.0, 0.8, -1.0, 0.6, -0.6, -1.6)


class Block:
    """settled: 1 within an article, -1 within boilerplate by sectioning tags alone, else 0."""

    __slots__ = ("text", "words", "linked", "prior", "settled", "parent", "tag")

    def __init__(self, text: str, linked: int, evidence: tuple[float, float, float], parent: int, tag: str):
        self.text, self.linked, self.prior, self.parent, self.tag = text, linked, sum(evidence), parent, tag
        content, by_tag, by_name = evidence
        self.settled = -1 if by_tag < 0 else int(content >= ARTICLE and not by_name)
        self.words = text.count(" ") + 1


def blocks_of(source: str) -> list[Block]:
    """Text blocks in page order, character references decoded and white space folded."""
    out: list[Block] = []
    stack: list[tuple[str, tuple[float, float, float], int]] = [("", (0.0, 0.0, 0.0), 0)]  # tag, evidence from here on, node
    node = 0
    pieces: list[str] = []
    linked: list[str] = []
    links = 0
    in_head = False
    skip = ""  # the element whose content is left out
    inner: list[str] = []  # elements open within it
    unclosed = False  # whether it has no end tag
    resume = -1  # where its first block begins, to be read from if it turns out to be unclosed
    endless: set[str] = set()  # elements with no end tag in the rest of the page

    def flush() -> None:
        if pieces:
            text = BLANKS.sub(" ", html.unescape("".join(pieces))).strip()
            if text:
                k = next((k for k in range(len(stack) - 1, 0, -1) if stack[k][0] in BLOCK_TAGS), 0)
                n_linked = len(html.unescape(" ".join(linked)).split())
                out.append(Block(text, n_linked, stack[-1][1], stack[max(k - 1, 0)][2], stack[k][0]))
            pieces.clear()
            linked.clear()

    def around(tag: str) -> bool:
        """Whether an element is open that this end tag closes."""
        for k in range(len(stack) - 1, 0, -1):
            if stack[k][0] == tag:
                return True
            if stack[k][0] in BLOCK_TAGS and tag not in BLOCK_TAGS:
                break
        return tag == "head" and in_head

    def end_of(tag: str, at: int) -> int:
        """Where the element's next end tag ends, -1 if there is none."""
        m = None if tag in endless else END_TAG[tag].search(source, at)
        if m is None:
            endless.add(tag)
        return m.end() if m else -1

    at = 0
    while True:
        m = TOKEN.search(source, at)
        if not skip and at < (m.start() if m else len(source)):
            piece = source[at : m.start()] if m else source[at:]
            in_head = in_head and piece.isspace()
            if not in_head:
                pieces.append(piece)
                if links and m:
                    linked.append(piece)
        if m is None:
            if skip and resume >= 0:
                at, skip = resume, ""
                continue
            break
        at = m.end()
        if m[2] is None:
            if m[0].startswith("<![CDATA[") and not skip:
                pieces.append(html.escape(m[0][9:].removesuffix("]]>")))
            continue
        tag = m[2].lower()
        closed = m[0].endswith("/>")
        if skip:
            if m[1]:
                if tag in inner:
                    del inner[len(inner) - 1 - inner[::-1].index(tag) :]
                    continue
                if tag == skip:
                    skip = ""
                    continue
                if not around(tag):
                    continue
                skip = ""
            elif tag == skip and tag in ("button", "select"):  # these do not nest: the open one ends
                skip = ""
                if resume < 0 and tag == "select":
                    continue
            else:
                if tag == "body" or tag in BLOCK_TAGS and tag not in ("option", "legend"):
                    if unclosed:
                        skip = ""
                    elif resume < 0:
                        resume = m.start()
                if skip:
                    if tag in RAW_TAGS and not closed and (end := end_of(tag, at)) >= 0:
                        at = end
                    elif tag in ("script", "style") and not closed:
                        at = len(source)
                    elif tag not in VOID and not closed:
                        inner.append(tag)
                    continue
            if resume >= 0:
                at, resume = resume, -1
                continue
        if in_head:
            if m[1]:
                in_head = tag not in ("head", "body", "html")
                if in_head or tag == "head":
                    continue
            else:
                in_head = tag in HEAD_TAGS
        elif m[1] and tag == "head":
            continue
        if not m[1] and tag == "head":
            in_head = not closed
            continue
        if m[1]:
            if tag in BLOCK_TAGS:
                flush()
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] == tag:
                    links -= sum(t[0] == "a" for t in stack[k:])
                    del stack[k:]
                    break
                if stack[k][0] in BLOCK_TAGS and tag not in BLOCK_TAGS:
                    break
            continue
        if tag in SKIPPED:
            if not closed:
                end = end_of(tag, at)
                if tag in RAW_TAGS and end >= 0:
                    at = end
                elif tag in ("script", "style"):
                    at = len(source)
                else:
                    skip, inner, unclosed, resume = tag, [], end < 0, -1
            pieces.append(" ")
            continue
        if tag in BLOCK_TAGS:
            flush()
            shut = CLOSED_BY_SIBLING.get(tag, frozenset(["p"]))
            for k in range(len(stack) - 1, 0, -1):
                if stack[k][0] in shut:
                    links -= sum(t[0] == "a" for t in stack[k:])
                    del stack[k:]
                    break
                if stack[k][0] in BLOCK_TAGS:
                    break
        if tag in SPACE_TAGS:
            pieces.append(" ")
        if tag in VOID or closed:
            continue
        node += 1
        stack.append((tag, _evidence(tag, m[3], stack), node))
        links += tag == "a"
    flush()
    return out


def _evidence(tag: str, attributes: str, stack: list[tuple[str, tuple[float, float, float], int]]) -> tuple[float, float, float]:
    """Log-odds of content for what stands inside this element, by content, by boilerplate tags and by boilerplate names."""
    content, by_tag, by_name = stack[-1][1]
    inside = content >= ARTICLE
    if tag in BOILER_TAGS and not (tag == "header" and inside):  # a heading block inside an article is part of it
        by_tag = BOILER
    starts = tag in CONTENT_TAGS
    named = 0.0
    for name, *values in ATTR.findall(attributes) if attributes else ():
        name, value = name.lower(), "".join(values)
        if name == "role":
            starts = starts or value.lower() in ("main", "article")
        if name == "role" and value.lower() in BOILER_ROLE or name == "aria-hidden" and value == "true" or name == "style" and re.search(r"display\s*:\s*none", value):
            by_tag = BOILER
        if name in ("class", "id") and tag not in ("html", "body"):
            if BOILER_NAME.search(value) or not inside and HEAD_NAME.search(value):
                named = BOILER if tag not in PARAGRAPHS else PARAGRAPH
            elif CONTENT_NAME.search(value):
                content = max(content, CONTENT)
    if starts:
        content = ARTICLE
        by_name = max(by_name, PARAGRAPH)  # the names around an article often tell of the page's layout
    return content, by_tag, min(by_name, named)


def features(b: Block) -> tuple[float, ...]:
    words = b.words
    stops = sum(b.text.count(c) for c in ".!?")
    return (math.log1p(words), min(1.0, b.linked / words), min(1.0, stops / words), float(b.text[-1] in ".!?\"'”»"), sum(w[:1].isupper() for w in b.text.split(" ")) / words, float(b.tag[:1] == "h" and b.tag[1:].isdigit()), float(b.tag in ("li", "dd", "dt", "option")), 1.0)


def score(b: Block, weights: tuple[float, ...]) -> float:
    """Log-odds of content: those of tags and names plus those of the text."""
    text = sum(w * x for w, x in zip(weights, features(b)))
    return b.prior + max(-TEXT_BOUND, min(TEXT_BOUND, text))


def minimum_cut(odds: list[float], edges: list[tuple[int, int, float]]) -> list[bool]:
    """Content side of the cheapest cut: a block on the wrong side pays |odds|, an edge between the sides its capacity."""
    n = len(odds)
    source, sink = n, n + 1
    cap: list[dict[int, float]] = [{} for _ in range(n + 2)]

    def add(u: int, v: int, c: float, back: float) -> None:
        cap[u][v] = cap[u].get(v, 0.0) + c
        cap[v][u] = cap[v].get(u, 0.0) + back

    for i, x in enumerate(odds):
        if x > 0:
            add(source, i, x, 0.0)
        elif x < 0:
            add(i, sink, -x, 0.0)
    for i, j, c in edges:
        add(i, j, c, c)
    while True:
        level = {source: 0}
        queue = [source]
        for u in queue:
            for v, c in cap[u].items():
                if c > 1e-9 and v not in level:
                    level[v] = level[u] + 1
                    queue.append(v)
        if sink not in level:
            return [i in level for i in range(n)]
        todo = {u: iter(list(cap[u])) for u in level}
        path = [source]
        while path:  # all shortest augmenting paths, without recursion
            u = path[-1]
            if u == sink:
                flow = min(cap[a][b] for a, b in zip(path, path[1:]))
                for a, b in zip(path, path[1:]):
                    cap[a][b] -= flow
                    cap[b][a] = cap[b].get(a, 0.0) + flow
                k = next(k for k, (a, b) in enumerate(zip(path, path[1:])) if cap[a][b] <= 1e-9)
                del path[k + 1 :]
                continue
            for v in todo[u]:
                if cap[u][v] > 1e-9 and level.get(v) == level[u] + 1:
                    path.append(v)
                    break
            else:
                level[u] = -1
                path.pop()


def edges_of(found: list[Block]) -> list[tuple[int, int, float]]:
    """Capacities between neighbours, and between each block and the one before it in the same element."""
    edges = [(i, i + 1, NEAR) for i in range(len(found) - 1)]
    last: dict[int, int] = {}
    for i, b in enumerate(found):
        if b.parent in last:
            edges.append((last[b.parent], i, SIBLING))
        last[b.parent] = i
    return edges


def label(found: list[Block], weights: tuple[float, ...]) -> list[bool]:
    return minimum_cut([score(b, weights) for b in found], edges_of(found))


def extract(source: str, weights: tuple[float, ...] = START_WEIGHTS) -> str:
    found = blocks_of(source)
    return "\n".join(b.text for b, keep in zip(found, label(found, weights)) if keep)


def train(pages: DataFrame, html_col: str = "html", sample: int = TRAIN_PAGES) -> tuple[float, ...]:
    """Logistic weights of the text from the blocks that sectioning tags label, on at most `sample` pages picked by a hash."""
    few = sample_rows(pages, sample).select(F.col(html_col).cast("string").alias("html")).where("html IS NOT NULL")

    def rows(source):
        for (text,) in source:
            for b in blocks_of(text):
                if b.settled:
                    yield (float(b.settled > 0), list(features(b)))

    # one row for each feature pattern: few, as the sample is bounded
    seen = map_rows(few, [F.col("html")], "label double, x array<double>", rows).groupBy("label", F.transform("x", lambda v: F.round(v, 2)).alias("x")).agg(F.count("*").alias("n")).collect()
    weights = np.array(START_WEIGHTS)
    if len({r.label for r in seen}) == 2:
        x, y, n = np.array([r.x for r in seen]), np.array([r.label for r in seen]), np.array([r.n for r in seen], float)
        n /= n.sum()
        prior = weights.copy()
        for _ in range(300):  # gradient steps towards the data, held near the start weights
            p = 1 / (1 + np.exp(-np.clip(x @ weights, -30, 30)))
            weights = weights - 0.5 * (x.T @ (n * (p - y)) + 0.01 * (weights - prior))
    return tuple(float(w) for w in weights)


def main_texts(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars) of every page."""
    weights = train(pages, html_col)

    def rows(source):
        for key, url, page in source:
            text = extract(page or "", weights)
            yield key, url, text, len(text)

    return map_rows(pages, [F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string"), F.col(html_col).cast("string")], "page_id long, url string, text string, n_chars long", rows)
