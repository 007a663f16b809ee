"""HTML extraction by minimum-cut labelling.

A page becomes blocks of text in page order, each in a tree of elements. A linear classifier gives each block the cost of calling it
content and of calling it boilerplate; these are the capacities to the two terminals. Neighbours in page order and siblings in the tree
are joined by smoothness edges that weaken with their distance in the tree. The minimum cut labels the blocks; a few words of
evidence and an edge weigh alike, so that short, linked or odd blocks go with what is around them.

What markup says is evidence, too, and no veto. An element speaks by its name and by the words of its class, id and role. The innermost
one that speaks counts, but navigation, footers, comments and the like speak for all inside them. An element that holds the page's
article or most of its paragraphs is a wrapper and does not speak, and neither does a name that says what a page has or lacks
(with-sidebar, no-ads). An article inside an article is a comment on it. A heading such as Comments or Related speaks for what
follows it in its element. Where nothing on a page comes out as content, the classifier's start is lifted for what neither markup nor
links speak against, until the best block leans to content.

Defined results: a null, empty or blank page has an empty text; broken markup is read as far as it goes (an unfinished tag at the end is
dropped, open elements end with the page); a page without markup is one block. Repeated rows give repeated results. Columns beyond
id, url and html are not read.
"""

from __future__ import annotations

import html
import math
import re
from collections import deque
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parinflate.runtime import ship, table

#: Elements by role.
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre search section summary table caption tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
SKIPPED = frozenset("head script style noscript template iframe object svg math canvas audio video select button textarea title datalist".split())
RAW = frozenset("script style textarea title iframe noscript".split())
#: Words of class, id and role, and elements, by what they say. Those of the first group speak for all inside.
CLOSED_TAGS = frozenset("nav footer aside menu dialog search form".split())
CLOSED_CUES = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion cookie cookies consent gdpr nav navigation navbar breadcrumb breadcrumbs footer share sharing social related recommended recommendations comment comments disqus reply replies respond responses discussion subscribe subscription newsletter signup pagination pager contentinfo complementary".split()
)
COMMENT_CUES = frozenset("comment comments disqus reply replies respond responses discussion".split())
OPEN_CUES = frozenset("banner notice notices alert menu menus sidebar side header masthead login popup modal overlay widget toolbar tags legal copyright disclaimer skip rss search dialog top topbar meta aside".split())
CONTENT_TAGS = frozenset("article main".split())
CONTENT_CUES = frozenset("article main content post entry story maincontent articlebody".split())
#: In a name with one of these the others say what a page has or lacks.
ABOUT = frozenset("with has have no non not without free less enabled disabled open closed on off layout page wrapper container body".split())
#: Headings of what is not the article, in the languages of the pages; a count may lead them.
SECTION = re.compile(r"(?:\d+\s+)?(?:(?:user |reader |leave a |post a )?(?:comments?|repl(?:y|ies)|responses?|discussion)|related(?: (?:posts|articles|stories|links))?|(?:see|read) also|more (?:stories|articles|from .*)|kommentare?|ähnliche artikel|mehr zum thema|commentaires?|articles (?:liés|similaires)|comentarios?|artículos relacionados)(?:\s*\(\d+\))?\s*:?", re.I)
#: Weights of the classifier: a start, the log of the words, the share of them in links, an end of a sentence, the kind of element, and what markup says.
BIAS, PER_LOG_WORD, LINKED, SENTENCE, HEADING, PARAGRAPH, ITEM = -3.0, 0.9, -4.0, 0.6, 1.0, 1.0, -0.5
IN_CONTENT, IN_CLOSED, IN_OPEN, IN_CUE = 2.5, -4.0, -3.0, 2.0
#: To what the best block of a page leans at least.
LEAST = 1.5
#: Weights of smoothness.
SMOOTH, DECAY, SIBLING = 1.0, 2.5, 0.5

_ATTRIBUTES = r"(?:[\s/]++|[^\s/>][^\s/>=]*+(?:\s*+=\s*+(?:\"[^\"]*+\"|'[^']*+'|[^\s>\"'][^\s>]*+|(?=>)))?+)*+"
_token = re.compile(rf"<!--.*?(?:-->|\Z)|<[!?][^>]*+(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*+)({_ATTRIBUTES})(>|\Z)", re.S)
_attribute = re.compile(r"""([^\s/>][^\s/>=]*+)(?:\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s>"'][^\s>]*+)))?""")
_split = re.compile(r"[\s_\-:/]+|(?<=[a-z])(?=[A-Z])")


class Element:
    """An open or closed element: what it says and what it holds."""

    __slots__ = ("name", "parent", "number", "evidence", "closed", "hides", "comments", "paragraphs", "holds")

    def __init__(self, name: str, parent: Element | None, number: int):
        self.name, self.parent, self.number = name, parent, number
        self.evidence, self.closed, self.hides = 0.0, False, parent is not None and parent.hides
        self.paragraphs = 0
        self.holds = self.comments = False  # an article or main element; comments by its own words


class Block:
    __slots__ = ("text", "at", "path", "linked", "chars", "heading", "after", "parts", "words")

    def __init__(self, at: Element | None, heading: bool):
        self.at, self.heading, self.after = at, heading, False
        self.parts: list[str] = []
        self.linked = self.chars = self.words = 0
        self.text = ""
        path = []
        while at is not None:
            path.append(at.number)
            at = at.parent
        self.path = tuple(reversed(path))


def _say(e: Element, attributes: str) -> None:
    """What an element says by its name and attributes; zero: nothing."""
    name, inside = e.name, e.parent
    while inside is not None and inside.name != "article":
        inside = inside.parent
    closed, open_, content = name in CLOSED_TAGS, name == "header" and inside is None, name in CONTENT_TAGS
    if name == "article" and inside is not None:  # a comment on the outer one
        closed, content = True, False
    cue = False
    for key, a, b, c in _attribute.findall(attributes) if attributes else ():
        key, value = key.lower(), html.unescape(a or b or c)
        if key in ("class", "id", "role") and name not in ("html", "body"):
            for one in value.split():
                words = {w.lower() for w in _split.split(one)}
                if words.isdisjoint(ABOUT):
                    closed |= not words.isdisjoint(CLOSED_CUES)
                    e.comments |= not words.isdisjoint(COMMENT_CUES)
                    open_ |= not words.isdisjoint(OPEN_CUES) and (inside is None or one.lower() in ("sidebar", "notice", "banner", "widget"))
                    cue |= not words.isdisjoint(CONTENT_CUES)
        elif key == "style":
            e.hides |= bool(re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I))
        elif key == "hidden" or key == "aria-hidden" and value == "true":
            e.hides = True
    e.closed = closed
    e.evidence = IN_CLOSED if closed else IN_CONTENT if content else IN_OPEN if open_ else IN_CUE if cue else 0.0


def blocks(page: str) -> list[Block]:
    """The text blocks of a page in page order."""
    out: list[Block] = []
    stack: list[Element] = []
    number = links = 0
    current: Block | None = None
    at, end = 0, len(page)

    def close(upto: int) -> None:
        nonlocal current
        del stack[upto:]
        current = None

    def add(text: str) -> None:
        nonlocal current
        if stack and stack[-1].hides:
            return
        if current is None:
            if not text.strip():
                return
            current = Block(stack[-1] if stack else None, any(x.name in HEADINGS for x in stack[-2:]))
            out.append(current)
        current.parts.append(text)
        n = len(text.strip())
        current.chars += n
        if links:
            current.linked += n

    while at < end:
        m = _token.search(page, at)
        if m is None:
            add(page[at:])
            break
        if m.start() > at:
            add(page[at : m.start()])
        at = m.end()
        name = m.group(2)
        if name is None or not m.group(4):
            continue  # a comment, a declaration, or a tag that the page does not finish
        name, closing, attributes = name.lower(), m.group(1), m.group(3)
        if name in RAW and not closing:
            at = _raw_end(name).search(page, at).end()
            continue
        if name == "a":
            links = 0 if closing else 1
        elif name == "br":
            add(" ")
        elif name in BLOCK or name in SKIPPED:
            links = 0
            if closing:
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k].name == name:
                        close(k)
                        break
                else:
                    current = None
                continue
            while stack and stack[-1].name in ENDED_BY.get(name, P_ONLY if name in BLOCK else ()):
                close(len(stack) - 1)
            current = None
            if name in VOID or attributes.endswith("/") and name in SKIPPED:
                continue
            number += 1
            e = Element(name, stack[-1] if stack else None, number)
            _say(e, attributes)
            e.hides |= name in SKIPPED
            if e.name in CONTENT_TAGS and e.evidence > 0 and not e.hides:
                up = e.parent
                while up is not None and not up.holds:
                    up.holds, up = True, up.parent
            stack.append(e)
    for b in out:
        b.text = " ".join(html.unescape("".join(b.parts)).split())
        b.words = b.text.count(" ") + 1
    return _placed([b for b in out if b.text])


@lru_cache
def _raw_end(name: str) -> re.Pattern:
    return re.compile(rf"</{name}(?=[\s/>])[^>]*+>|\Z", re.I)


def _placed(bs: list[Block]) -> list[Block]:
    """Count what each element holds, and find the blocks after headings of other sections."""
    total = 0
    for b in bs:
        long = b.words > 8 and b.linked < 0.3 * b.chars
        total += long
        e = b.at
        while e is not None:
            e.paragraphs += long
            e = e.parent
    for e in {id(e): e for b in bs for e in _up(b.at)}.values():
        # A wrapper: of the page's article, or of most paragraphs of a page that has no such element and nothing else to be read.
        if e.evidence < 0 and e.name not in ("nav", "footer", "aside", "article") and not e.comments and (e.holds or e.name == "form" and 2 * e.paragraphs > total > 2):
            e.evidence, e.closed = 0.0, False
    ends: list[tuple[int, int]] = []  # (depth of the element, its number) in which a section of comments has begun
    for b in bs:
        ends = [x for x in ends if len(b.path) >= x[0] and (x[0] == 0 or b.path[x[0] - 1] == x[1])]
        b.after = bool(ends)
        if b.heading and SECTION.fullmatch(b.text):
            b.after = True
            depth = len(b.path) - 1
            ends.append((depth, b.path[depth - 1] if depth else 0))
    return bs


def _up(e: Element | None) -> Iterator[Element]:
    while e is not None:
        yield e
        e = e.parent


HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
P_ONLY = ("p", *sorted(HEADINGS))
ENDED_BY = {"li": (*P_ONLY, "li"), "dt": (*P_ONLY, "dt", "dd"), "dd": (*P_ONLY, "dt", "dd"), "tr": (*P_ONLY, "td", "th", "tr"), "td": (*P_ONLY, "td", "th"), "th": (*P_ONLY, "td", "th"), "body": (*P_ONLY, "head")}


def evidence(b: Block) -> float:
    """What markup says of a block: the innermost element that speaks, unless one around it speaks for all inside."""
    said = 0.0
    for e in _up(b.at):
        if e.closed:
            return IN_CLOSED
        said = said or e.evidence
    return said


def leaning(b: Block) -> float:
    """Cost of calling a block boilerplate less that of calling it content: the log odds of the classifier."""
    name = b.at.name if b.at is not None else ""
    z = BIAS + PER_LOG_WORD * math.log1p(b.words) + LINKED * b.linked / max(1, b.chars)
    z += SENTENCE * (b.text[-1] in ".!?…\"'”»") + HEADING * b.heading + PARAGRAPH * (name == "p") + ITEM * (name in ("li", "td", "th", "dt", "dd"))
    return z + evidence(b) + IN_CLOSED * b.after


def edges(bs: list[Block]) -> list[tuple[int, int, float]]:
    """Smoothness: page neighbours by their distance in the tree, and consecutive siblings that something else parts."""
    out, last = [], {}
    for i, b in enumerate(bs):
        if i:
            a, c = bs[i - 1].path, b.path
            k = 0
            for x, y in zip(a, c, strict=False):
                if x != y:
                    break
                k += 1
            out.append((i - 1, i, SMOOTH * math.exp(-DECAY * max(0, len(a) + len(c) - 2 * k - 2))))
        parent = b.path[:-1]
        if last.get(parent, i - 1) != i - 1:
            out.append((last[parent], i, SIBLING))
        last[parent] = i
    return out


def min_cut(lean: list[float], links: list[tuple[int, int, float]]) -> list[bool]:
    """Labels (true: content) of least cost. Nodes whose lean outweighs all their edges are settled first; max-flow cuts the rest."""
    n = len(lean)
    z = list(lean)
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for i, j, w in links:
        near[i][j] = near[i].get(j, 0.0) + w
        near[j][i] = near[j].get(i, 0.0) + w
    label: list[bool | None] = [None] * n
    todo = deque(range(n))
    while todo:
        i = todo.popleft()
        if label[i] is not None or abs(z[i]) < sum(near[i].values()) or not z[i] and near[i]:
            continue
        label[i] = z[i] > 0
        for j, w in near[i].items():
            z[j] += w if label[i] else -w
            del near[j][i]
            todo.append(j)
        near[i] = {}
    core = [i for i in range(n) if label[i] is None]
    if core:
        side = _flow(core, z, near)
        for i in core:
            label[i] = i in side
    return [bool(x) for x in label]


def _flow(core: list[int], z: list[float], near: list[dict[int, float]]) -> set[int]:
    """The source side of a minimum cut, by shortest augmenting paths with level graphs."""
    source, sink, eps = -1, -2, 1e-9
    cap: dict[int, dict[int, float]] = {source: {}, sink: {}, **{i: dict(near[i]) for i in core}}
    for i in core:
        if z[i] > 0:
            cap[source][i] = z[i]
            cap[i][source] = 0.0
        else:
            cap[i][sink] = -z[i]
            cap[sink][i] = 0.0
    while True:
        level, queue = {source: 0}, deque([source])
        while queue:
            u = queue.popleft()
            for v, c in cap[u].items():
                if c > eps and v not in level:
                    level[v] = level[u] + 1
                    queue.append(v)
        if sink not in level:
            return {u for u in level if u >= 0}
        nexts = {u: list(cap[u]) for u in level}
        path = [source]
        while path:
            u = path[-1]
            if u == sink:
                least = min(cap[a][b] for a, b in zip(path, path[1:], strict=False))
                for a, b in zip(path, path[1:], strict=False):
                    cap[a][b] -= least
                    cap[b][a] = cap[b].get(a, 0.0) + least
                path = [source]
                continue
            while nexts[u] and not (cap[u].get(nexts[u][-1], 0.0) > eps and level.get(nexts[u][-1], -1) == level[u] + 1):
                nexts[u].pop()
            if nexts[u]:
                path.append(nexts[u][-1])
            else:
                path.pop()
                if path:
                    nexts[path[-1]].pop()


def extract(page: str | None) -> str:
    """The main text of a page: content blocks in page order, one per line."""
    if not page:
        return ""
    bs = blocks(page)
    return "\n".join(b.text for b, k in zip(bs, labels(bs), strict=True) if k)


def labels(bs: list[Block]) -> list[bool]:
    """Which blocks of a page are content."""
    lean, links = [leaning(b) for b in bs], edges(bs)
    keep = min_cut(lean, links)
    if any(keep):
        return keep
    free = [evidence(b) >= 0 and not b.after and 2 * b.linked < b.chars for b in bs]
    lift = LEAST - max((z for z, f in zip(lean, free, strict=True) if f), default=LEAST)
    return min_cut([z + lift * f for z, f in zip(lean, free, strict=True)], links)


def _run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = [extract(x.as_py()) for x in batch.column(2)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])


def main_text(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars) of every row."""
    ship(pages.sparkSession)
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    return rows.mapInArrow(_run, "page_id long, url string, text string, n_chars long")


def op1_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text(table(spark, sf_dir, "pages"))
