"""Main text of a page by tag-path ratios.

A page's text falls into blocks; a block's tag path runs from the root to the element that holds it. For every path
the length of text and the count of punctuation, each per block and lessened by linked text, are gathered; the
series of both along the page is smoothed with a Gaussian, smoothed and plain ones are fused, and blocks whose path is above a
threshold that the page itself sets are content. What an element says of itself is a prior on the scores of the paths through it:
an article's are raised, those of classes that name comments, adverts and the like are lowered. The ratios decide on every page.
Blocks that stand among the content, in the element that holds most of it, go with it (a list inside a story), and so does a
heading with the content it stands before. Only elements that by their name or role never hold an article's text count nothing.

A null or empty page gives an empty text. Markup may be broken: unclosed elements end with their parent, stray end tags
are passed over, and an unclosed script or style runs to the end of the page. A head ends where something stands that no head holds. Of elements
without article text (drawings, choices, embedded objects) nothing is read; one that is never closed is passed over as a mere tag. Repeated rows are
treated each on its own. Memory grows with the page alone, however deep its elements nest: an element keeps a number for its path and
one for its parent.
"""

from __future__ import annotations

import html as _html
import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tabqa.llm.common import map_arrow

# Element names by their part in a page.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr br img".split())
#: Their content is no markup.
RAW = frozenset("script style textarea iframe title".split())
#: Their content is markup, and no text of the page; those of FRAGILE end where a block begins.
SKIPPED = frozenset("noscript template svg math object select".split())
FRAGILE = frozenset("svg math select".split())
IN_HEAD = frozenset("base link meta title style script noscript template".split())
ASIDE = frozenset("nav footer aside form button menu dialog fieldset".split())
ASIDE_ROLES = frozenset("navigation banner contentinfo complementary search dialog alertdialog menu menubar".split())
ARTICLE = frozenset("article main".split())
CLOSES_P = frozenset("address article aside blockquote div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
SAME_CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("td", "th", "tr"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
CONTAINERS = frozenset("ul ol dl table div section article main body html nav aside footer header form blockquote".split())
#: Words of classes and ids: of what isn't the article, of what is, and such as tell nothing of either.
MARKS = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner nav navbar navigation menu breadcrumb breadcrumbs sidebar aside footer masthead "
    "cookie cookies consent gdpr notice notices newsletter subscribe subscription signup share sharing social related recommended comment comments reply replies respond disqus "
    "discussion popup modal overlay login search widget pagination pager toc copyright legal disclaimer complementary contentinfo topbar".split()
)
OWN = frozenset("article articles content contents post posts story entry main body text page news blog prose".split())
PLAIN = frozenset(
    "a area bar block bottom box button buttons byline center col column container footer form group header head holder icon icons inner item items left level line link links list "
    "module outer panel pane primary region right row secondary section sections site slot small strip sub thread title top unit user view wrap wrapper area large medium mini".split()
)
#: What the score of a path is multiplied by: through a declared article, through a marked element, and through one that is marked but says that it is the article as well.
RAISED, LOWERED, CONTESTED = 2.0, 0.02, 0.8
#: A block of so much text and so many marks is as good as a longer one, so that one long block doesn't outdo all others.
FULL_TEXT, FULL_MARKS = 400, 8
#: Least share of the page's highest score.
LEAST = 0.15
#: Share of the chosen text that the element has which holds the content.
HOLDS = 0.6
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^<>\"']++|\"[^\"]*+\"|'[^']*+'|[\"'])*+)>|<[!?][^>]*>", re.S)
_MARKED = re.compile(r"(?<![\w-])(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_HIDDEN = re.compile(r"(?<![\w-])hidden(?![\w-])|display\s*:\s*none", re.I)
_HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
_LISTED = frozenset("li dt dd td th pre blockquote figcaption caption p".split()) | _HEADINGS
_PUNCTUATION = re.compile(r"[.,;:!?…。，、！？]")
_WORDS = re.compile(r"[a-z0-9]+")


@dataclass
class Block:
    """A text block: its path's number, its text, how much of it is linked, its path's prior, and the element that holds it."""

    path: int
    text: str
    linked: int
    prior: float
    element: int


@dataclass
class Page:
    """A page's blocks in order, and its elements: parent and name of each, in the order in which they begin; 0 is the root."""

    blocks: list[Block] = field(default_factory=list)
    parents: list[int] = field(default_factory=lambda: [0])
    names: list[str] = field(default_factory=lambda: [""])
    priors: list[float] = field(default_factory=lambda: [1.0])


def _says(attributes: str) -> tuple[bool, bool, bool, tuple[str, ...]]:
    """Whether an element's class and id mark it, whether they declare the article, whether its role rules it out, and its class words."""
    marked = own = out = False
    words: list[str] = []
    for m in _MARKED.finditer(attributes):
        for name in (m[2] or m[3] or m[4] or "").lower().split():
            parts = _WORDS.findall(name)
            if m[1].lower() == "role":
                out |= name in ASIDE_ROLES
                own |= name in ARTICLE
            elif any(p in MARKS for p in parts) and all(p in MARKS or p in PLAIN or p in OWN or p.isdigit() or len(p) < 2 for p in parts):
                marked = True
            elif any(p in OWN for p in parts) and not any(p in MARKS for p in parts):
                own = True
            if m[1].lower() == "class":
                words += [p for p in parts if p.isalpha()]
    return marked, own, out, tuple(sorted(set(words)))


@dataclass(slots=True)
class _Open:
    """An open element. `holder` is the innermost one that isn't inline; a null path tells that nothing is read inside."""

    name: str
    path: int | None
    prior: float
    element: int
    inside: bool
    holder: _Open | None = None


def blocks_of(page: str) -> Page:
    """The page's text blocks in order. Each step costs what it closes, so that deep nesting stays linear."""
    out = Page()
    blocks = out.blocks
    root = _Open("", 0, 1.0, 0, False)
    root.holder = root
    stack: list[_Open] = []
    scopes: list[dict[str, int]] = [{}]  # open elements by name, within each open container
    open_by_name: dict[str, int] = {}
    numbers: dict[tuple, int] = {}
    parts: list[str] = []
    linked = links = unread_at = 0  # unread_at: the depth from which nothing is read, plus one
    at = 0
    lower = re.sub("[A-Z]+", lambda m: m[0].lower(), page)
    last: dict[str, int] = {}  # where the last end tag of a name stands

    def never_closed(name: str) -> bool:
        if name not in last:
            last[name] = max((m.start() for m in re.finditer(rf"</{name}(?=[\s/>])", lower)), default=-1)
        return last[name] < at

    def push(entry: _Open) -> None:
        nonlocal links, unread_at
        stack.append(entry)
        name = entry.name
        open_by_name[name] = open_by_name.get(name, 0) + 1
        if name in CONTAINERS:
            scopes.append({})
        else:
            scopes[-1][name] = scopes[-1].get(name, 0) + 1
        links += name == "a"
        if entry.path is None and not unread_at:
            unread_at = len(stack)

    def pop() -> _Open:
        nonlocal links, unread_at
        entry = stack.pop()
        name = entry.name
        open_by_name[name] -= 1
        if name in CONTAINERS:
            scopes.pop()
        else:
            scopes[-1][name] -= 1
        links -= name == "a"
        if unread_at > len(stack):
            unread_at = 0
        return entry

    def end_block() -> None:
        nonlocal linked
        if parts:
            text = " ".join(_html.unescape("".join(parts)).split())
            if text:
                holder = stack[-1].holder if stack else root
                blocks.append(Block(holder.path, text, linked, holder.prior, holder.element))
            parts.clear()
            linked = 0

    def add(text: str) -> None:
        nonlocal linked
        if stack and stack[-1].name == "head" and text.strip():
            close(len(stack) - 1)
        if text and not unread_at:
            parts.append(text)
            if links:
                linked += len(text)

    def close(depth: int) -> None:
        if any(s.name not in INLINE and s.path is not None for s in stack[depth:]):
            end_block()
        while len(stack) > depth:
            pop()

    def close_in_scope(names: tuple[str, ...]) -> None:
        """Closes the innermost open element of one of the names, if it stands in the innermost container."""
        if any(scopes[-1].get(n) for n in names):
            depth = len(stack) - 1
            while stack[depth].name not in names:
                depth -= 1
            close(depth)

    while m := _TOKEN.search(page, at):
        add(page[at : m.start()])
        at = m.end()
        if not m[2]:
            continue
        name = m[2].lower()
        if m[1]:
            if open_by_name.get(name) if name in CONTAINERS else scopes[-1].get(name):
                depth = len(stack) - 1
                while stack[depth].name != name:
                    depth -= 1
                close(depth)
            continue
        # what ends a part of which nothing is read: a head's end by its content, a body, a block in a drawing or a choice
        if unread_at:
            first = stack[unread_at - 1].name
            if name == "body" or first in FRAGILE and name in CLOSES_P and not open_by_name.get("foreignobject"):
                close(unread_at - 1)
            elif stack[-1].name == "head" and name not in IN_HEAD:
                close(len(stack) - 1)
        if name in VOID:
            if name == "br":
                add(" ")
            elif name == "hr" and not unread_at:
                end_block()
            continue
        ended = m[3].rstrip().endswith("/")
        if name in RAW:
            if not ended:
                if found := None if never_closed(name) else re.compile(rf"</{name}[\s/][^>]*>|</{name}>").search(lower, at):
                    at = found.end()
                elif name in ("script", "style"):
                    at = len(page)
                else:  # up to the next tag
                    following = _TOKEN.search(page, at)
                    at = following.start() if following else len(page)
            continue
        if unread_at or name == "head" or name in SKIPPED:
            if unread_at and stack[-1].name in SAME_CLOSES.get(name, ()):
                pop()
            if not ended and not (name in SKIPPED and never_closed(name)):
                push(_Open(name, None, 0.0, 0, False, stack[-1].holder if stack else root))
            continue
        if name not in INLINE:
            if name in CLOSES_P:
                close_in_scope(("p",))
            if name in SAME_CLOSES:
                close_in_scope(SAME_CLOSES[name])
            end_block()
        holder = stack[-1].holder if stack else root
        if name in INLINE:
            entry = _Open(name, holder.path, holder.prior, holder.element, holder.inside, holder)
        else:
            marked, own, ruled_out, words = _says(m[3]) if m[3] else (False, False, False, ())
            prior, inside = holder.prior, holder.inside
            if name in ASIDE or ruled_out or (name == "header" and not inside) or m[3] and _HIDDEN.search(m[3]):
                prior = 0.0
            elif name not in ("body", "html"):
                if marked:
                    prior *= CONTESTED if own else LOWERED
                elif name in ARTICLE and not inside:
                    prior *= RAISED
                inside |= name in ARTICLE or own
            out.parents.append(holder.element)
            out.names.append(name)
            out.priors.append(prior)
            path = numbers.setdefault((holder.path, name, words), len(numbers) + 1)
            entry = _Open(name, path, prior, len(out.parents) - 1, inside)
            entry.holder = entry
        push(entry)
    add(page[at:])
    end_block()
    return out


def _smooth(values: np.ndarray, sigma: float = 1.0) -> np.ndarray:
    reach = np.arange(-2, 3)
    kernel = np.exp(-(reach**2) / (2 * sigma * sigma))
    over = np.convolve(np.ones(len(values)), kernel, "full")[2:-2]
    return np.convolve(values, kernel, "full")[2:-2] / over


def path_scores(blocks: list[Block]) -> np.ndarray:
    """For each block the fused ratio of its path times the path's prior."""
    paths = np.unique([b.path for b in blocks], return_inverse=True)[1]
    own = np.array([max(0, len(b.text) - b.linked) for b in blocks], float)
    marks = np.array([len(_PUNCTUATION.findall(b.text)) * (own[i] / max(1, len(b.text))) for i, b in enumerate(blocks)])
    own, marks = np.minimum(own, FULL_TEXT), np.minimum(marks, FULL_MARKS)
    n = np.bincount(paths)
    text_ratio, mark_ratio = (np.bincount(paths, own) / n)[paths], (np.bincount(paths, marks) / n)[paths]
    plain = np.sqrt(text_ratio * (mark_ratio + 0.1))
    fused = np.sqrt(plain * np.sqrt(_smooth(text_ratio) * (_smooth(mark_ratio) + 0.1)))
    return (np.bincount(paths, fused) / n)[paths] * np.array([b.prior for b in blocks])


def _holding(page: Page, chosen: np.ndarray) -> int:
    """The innermost container that has the share HOLDS of the chosen blocks' text."""
    held = np.zeros(len(page.parents))
    for b, c in zip(page.blocks, chosen, strict=True):
        if c:
            held[b.element] += len(b.text) - b.linked
    total = held.sum()
    for i in range(len(held) - 1, 0, -1):  # children come after their parents
        held[page.parents[i]] += held[i]
    most = np.flatnonzero(held >= HOLDS * total)
    at = int(most[-1]) if total and len(most) else 0
    while at and page.names[at] not in CONTAINERS:
        at = page.parents[at]
    return at


def content_blocks(page: Page, share: float = 0.8) -> list[Block]:
    """The blocks whose path's score passes the page's threshold (`share` of its standard deviation, and LEAST of its highest score), and what goes with them."""
    blocks = page.blocks
    if not any(b.prior for b in blocks):
        return []
    score = path_scores(blocks)
    threshold = max(share * float(np.std(score)), LEAST * float(score.max())) if len(blocks) > 1 else 0.0
    chosen = (score >= threshold) & np.array([b.prior > 0 for b in blocks])
    # what stands in the element of the content and isn't lowered or mostly links goes with the content
    around = _holding(page, chosen)
    within = [False] * len(page.parents)
    within[around] = True
    for i in range(around + 1, len(within)):
        within[i] = within[page.parents[i]]
    whole = page.names[around] not in ("", "html", "body")
    at = np.flatnonzero(chosen)
    first, last = (int(at[0]), int(at[-1])) if len(at) else (0, -1)
    for i, b in enumerate(blocks):
        if not chosen[i] and within[b.element] and b.prior > 0 and b.prior >= page.priors[around] and 2 * b.linked <= len(b.text):
            chosen[i] = whole or first < i < last and page.names[b.element] in _LISTED
    for i in range(len(blocks) - 2, -1, -1):  # a heading goes with what it heads
        chosen[i] |= bool(chosen[i + 1] and blocks[i].prior > 0 and page.names[blocks[i].element] in _HEADINGS)
    return [b for b, c in zip(blocks, chosen, strict=True) if c]


def main_text(page: str | None) -> str:
    """The content blocks' texts, joined by an empty line."""
    return "\n\n".join(b.text for b in content_blocks(blocks_of(page))) if page else ""


def extract_pages(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: page_id, url, text, n_chars. Other columns of the pages, whatever their names, take no part."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [main_text(h) for h in batch.column(2).to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    kinds = dict(pages.dtypes)
    return map_arrow(pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).cast("string").alias("html")), run, f"page_id {kinds[id_col]}, url {kinds[url_col]}, text string, n_chars bigint")
