"""Main text of HTML pages: the maximum-scoring contiguous run of tokens.

Words score positive and tags negative, with weights learned from pages whose content element is marked; one
linear scan finds the best region. Elements that are never article text (menus, sidebars, notices, adverts, forms,
scripts, reader comments) are cut out first by name, role and class, and the region is then read block by block.
A null or empty page has the empty text. Unclosed and crossed tags are handled as browsers do, roughly; time grows with
the page and the depth of its elements, not with their product.
"""

from __future__ import annotations

import html as entities
import math
import re
from collections import Counter
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Elements whose content is markup or machinery, passed over up to their end tag.
RAW = frozenset("script style noscript template svg math iframe object canvas audio video textarea xmp noembed noframes".split())
#: Those of them that have no content where they close themselves or have no end tag, so that text behind them stays.
EMBEDS = frozenset("svg math iframe object canvas audio video".split())
#: Elements that are never part of an article.
ASIDE = frozenset("nav header footer aside form menu dialog button select option datalist fieldset label input head title".split())
ROLES = frozenset("navigation banner contentinfo complementary search form menu menubar dialog alertdialog alert note toolbar tablist".split())
#: Words of class and id values that name what is not the article.
HINTS = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner nav navbar navigation menu menus breadcrumb breadcrumbs header masthead footer foot sidebar aside widget widgets related recommended "
    "share sharing social cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login comment comments commentlist reply replies respond disqus pagination pager toolbar skip".split()
)
#: Those of them that count as a part of a value inside an article too, and as a whole value on the article itself,
#: which may hold a reader's comment or a teaser.
REPLIES = frozenset("comment comments commentlist reply replies respond disqus advert advertisement sponsored promo related recommended".split())
#: Elements that begin and end a block of text.
BLOCKS = frozenset(
    "address article blockquote body caption center dd details div dl dt figcaption figure h1 h2 h3 h4 h5 h6 hgroup hr html li main ol p pre section summary table tbody td tfoot th thead tr ul header footer nav aside form".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: An opening tag of these ends an open one of the same group.
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
CONTENT = frozenset(("article", "main"))
#: Elements that may hold a whole article, and those that hold a block of prose.
FRAMES = frozenset("div section td article main body html #root".split())
PROSE = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre li dd dt td th figcaption".split())

TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S)
ATTRIBUTE = re.compile(r"([^\s=\"'>/]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden")
WORDS_OF = re.compile(r"[a-z]+")

#: Learned by learn_weights() on the pages of a labelled set; these are used where none is given.
DEFAULT_WEIGHTS = {"word": 1.0, "tag": -1.0, "link": -4.0, "edge": -2.0}


def named_aside(name: str, raw: str, inside: bool = False) -> bool:
    """Whether an opening tag begins something that is not the article. Inside a marked article a value must be a hint
    as a whole: `header-note` may well be text there, `share` is not."""
    if name in ASIDE:
        return True
    if "=" not in raw and "hidden" not in raw:
        return False
    attributes = {m[1].lower(): next((x for x in m.groups()[1:] if x is not None), "") for m in ATTRIBUTE.finditer(raw)}
    if "hidden" in attributes or attributes.get("aria-hidden") == "true" or HIDDEN.search(attributes.get("style", "").lower()):
        return True
    if attributes.get("role", "").lower() in ROLES:
        return True
    if name in ("body", "html", "main"):
        return False
    values = f"{attributes.get('class', '')} {attributes.get('id', '')}"
    whole = values.lower().split()
    if name == "article":
        return not REPLIES.isdisjoint(whole)
    parts = WORDS_OF.findall(re.sub(r"([a-z])([A-Z])", r"\1 \2", values).lower())
    return not ((REPLIES if inside else HINTS).isdisjoint(parts) and HINTS.isdisjoint(whole))


class Page:
    """Tokens of a page: (kind, value, excluded, in_link, in_content, element). kind: text, block, break or inline."""

    __slots__ = ("tokens", "content", "parents", "names", "prose", "spans")

    def __init__(self, source: str):
        self.tokens: list[tuple[str, str, bool, bool, bool, int]] = []
        self.content = False
        #: of each element: its parent, its name, whether it is in a block of prose, and its first token and the one behind its last
        self.parents, self.names, self.prose, self.spans, ids = [-1], ["#root"], [False], [[0, 0]], [0]
        stack: list[tuple[str, bool]] = []  # open elements, and whether each begins an excluded part
        opened: Counter[str] = Counter()  # their names, so that an end tag of none of them costs nothing
        endless: set[str] = set()  # raw elements without an end tag from here on
        shut = links = inside = 0
        at, end = 0, len(source)

        def leave(upto: int) -> None:
            nonlocal shut, links, inside
            while len(stack) > upto:
                name, out = stack.pop()
                self.spans[ids.pop()][1] = len(self.tokens)
                opened[name] -= 1
                shut -= out
                links -= name == "a"
                inside -= name in CONTENT

        def innermost(names: set[str] | frozenset[str]) -> int | None:
            if not any(opened[x] for x in names):
                return None
            return next(i for i in range(len(stack) - 1, -1, -1) if stack[i][0] in names)

        while at < end:
            m = TOKEN.search(source, at)
            stop = m.start() if m else end
            if stop > at:
                self.tokens.append(("text", source[at:stop], shut > 0, links > 0, inside > 0, ids[-1]))
            if not m:
                break
            at = max(m.end(), stop + 1)
            if m[2] is None:
                if m[0].startswith("<![CDATA["):
                    self.tokens.append(("text", m[0][9:].removesuffix("]]>"), shut > 0, links > 0, inside > 0, ids[-1]))
                continue
            name, closing, empty = m[2].lower(), bool(m[1]), m[3].endswith("/")
            if closing:
                depth = innermost({name})
                # an end tag inside an excluded part only reaches across its edge if it closes the part's parent, as browsers have it
                if depth is not None:
                    leave(depth)
            elif name in RAW:
                if not (empty and name in EMBEDS):
                    close = None if name in endless else re.compile(rf"</{name}\b[^>]*(?:>|\Z)", re.I).search(source, at)
                    if close:
                        at = close.end()
                    elif name in EMBEDS:
                        endless.add(name)
                    else:
                        at = end
            else:
                if name in BLOCKS and stack and stack[-1][0] == "p":
                    leave(len(stack) - 1)
                if group := CLOSES.get(name):
                    depth = innermost(group | {"ul", "ol", "dl", "table", "select"})
                    if depth is not None and stack[depth][0] in group:
                        leave(depth)
                if name not in VOID and not empty:
                    out = named_aside(name, m[3], inside > 0)
                    if out and name == "header" and inside:
                        out = shut > 0
                    stack.append((name, out))
                    opened[name] += 1
                    self.prose.append(name in PROSE or self.prose[ids[-1]])
                    self.parents.append(ids[-1])
                    self.names.append(name)
                    self.spans.append([len(self.tokens), 0])
                    ids.append(len(self.names) - 1)
                    shut += out
                    links += name == "a"
                    inside += name in CONTENT
                    self.content |= name in CONTENT and not shut
            self.tokens.append(("block" if name in BLOCKS else "break" if name == "br" else "inline", name, shut > 0, links > 0, inside > 0, ids[-1]))
        leave(0)
        self.spans[0][1] = len(self.tokens)

    def scores(self, weights: dict[str, float]) -> list[float]:
        out = []
        was = False
        for kind, value, excluded, link, inside, _ in self.tokens:
            edge = weights["edge"] if excluded and not was else 0.0
            was = excluded
            if excluded:
                out.append(edge + (weights["tag"] if kind != "text" else 0.0))
            elif kind == "text":
                # words of a marked article count twice, and its links as words
                out.append(len(value.split()) * (weights["link"] if link and not inside else weights["word"] * (1 + (inside and not link))))
            else:
                out.append(weights["tag"])
        return out

    def region(self, weights: dict[str, float]) -> tuple[int, int]:
        """The best contiguous run of tokens of the whole page, by one scan; words of a marked article count twice."""
        best, best_at, total, start = 0.0, (0, 0), 0.0, 0
        for i, score in enumerate(self.scores(weights)):
            if total <= 0:
                total, start = 0.0, i
            total += score
            if total > best:
                best, best_at = total, (start, i + 1)
        return best_at

    def path(self, element: int) -> list[int]:
        out = []
        while element >= 0:
            out.append(element)
            element = self.parents[element]
        return out

    def widened(self, a: int, b: int) -> tuple[int, int]:
        """The run, out to the edges of the element that holds all its texts; under the body itself, out over the
        headings and paragraphs next to it, as short blocks at the edges can't pay for their tags."""
        said = [t[5] for t in self.tokens[a:b] if t[0] == "text" and not t[2] and t[1].strip()]
        if not said:
            return a, b
        last = set(self.path(said[-1]))
        common = next(x for x in self.path(said[0]) if x in last)
        while self.names[common] not in FRAMES and self.parents[common] > 0:
            common = self.parents[common]
        if self.names[common] not in ("body", "html", "#root"):
            first, behind = self.spans[common]
            return min(a, first), max(b, behind)

        def plain(i: int) -> bool:
            kind, value, excluded, link, _, element = self.tokens[i]
            if kind != "text" or not value.strip() or excluded:
                return True
            return not link and self.prose[element]

        while a and plain(a - 1):
            a -= 1
        while b < len(self.tokens) and plain(b):
            b += 1
        return a, b

    def text(self, weights: dict[str, float]) -> str:
        a, b = self.region(weights)
        if b > a:
            a, b = self.widened(a, b)
        blocks: list[list[str]] = [[]]
        for i, (kind, value, excluded, _, inside, _) in enumerate(self.tokens if b > a else []):
            if kind == "block":
                blocks.append([])
            if excluded or not (a <= i < b or inside):  # a marked article counts whole: its edges may hold short blocks
                continue
            if kind == "text":
                blocks[-1].append(entities.unescape(value))
            elif kind == "break":
                blocks[-1].append(" ")
        lines = (" ".join("".join(parts).split()) for parts in blocks)
        return "\n".join(line for line in lines if line)


def extract(source: str | None, weights: dict[str, float] | None = None) -> str:
    return Page(source).text(weights or DEFAULT_WEIGHTS) if source else ""


def learn_weights(sources: Iterable[str]) -> dict[str, float]:
    """Weights from labelled pages, whose article or main element is the label: the log ratio of how often a token
    of each kind stands inside the label and outside it, with words fixed at 1."""
    seen = {"word": [1.0, 1.0], "tag": [1.0, 1.0], "link": [1.0, 1.0]}
    for source in sources:
        page = Page(source)
        if not page.content:
            continue
        for kind, value, excluded, link, inside, _ in page.tokens:
            n = len(value.split()) if kind == "text" else 1
            seen[("link" if link else "word") if kind == "text" else "tag"][0 if inside and not excluded else 1] += n
    ratio = {k: math.log(a / b) for k, (a, b) in seen.items()}
    unit = max(ratio["word"], 0.1)
    out = {"word": 1.0, "tag": min(-0.5, (ratio["tag"] - ratio["word"]) / unit), "link": min(-1.0, (ratio["link"] - ratio["word"]) / unit)}
    return out | {"edge": 2.0 * out["tag"]}


def extract_pages(pages: DataFrame, weights: dict[str, float] | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) of each row; n_chars counts code points. Other columns are not read."""
    known = weights or DEFAULT_WEIGHTS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [extract(x, known) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    types = dict(pages.dtypes)
    return pages.select("page_id", "url", "html").mapInArrow(run, f"page_id {types['page_id']}, url {types['url']}, text string, n_chars long")


#: How many labelled pages weights are learned from at most.
LABELLED_PAGES = 500


def weights_from(pages: DataFrame, limit: int = LABELLED_PAGES) -> dict[str, float]:
    """Weights from a bounded sample of pages that mark their article, chosen by a hash so that tasks send only about as
    many rows as are wanted; the defaults where there is none."""
    there, draw = pages.count(), F.pmod(F.xxhash64("page_id", "url"), F.lit(1 << 30))
    some = pages.select("page_id", "url", "html").where(draw < F.lit(min(1 << 30, 2 * limit * (1 << 30) // max(1, there))))
    marked = some.where("lower(html) LIKE '%<article%' OR lower(html) LIKE '%<main%'").orderBy(draw, "html").limit(limit)
    sources = [r["html"] for r in marked.collect()]
    return learn_weights(sources) if sources else dict(DEFAULT_WEIGHTS)
