"""Main text of web pages by tag-path ratios.

Each text block has a path of element labels from the root. Per path, the mean text length and the mean
number of punctuation marks of its blocks are taken, smoothed over neighbouring blocks of the same section, multiplied, and
compared with their spread over the page; blocks of paths above it are content. Names of classes are a weak prior only: a section
that calls itself boilerplate goes if it holds less than half of the content, or is beside an article element. What is returned is, in page order, the
smallest section that holds the content, without those of its sections that hold none, and without menus of links.
"""

from __future__ import annotations

import html
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from replica_sync.llm.common import pick, small_batches

# Names of HTML elements by their role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = ("script", "style", "textarea", "title", "noscript", "template", "iframe", "xmp", "noembed", "noframes")
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr br".split())
DROPPED = frozenset("head script style noscript template iframe textarea title nav footer aside button select option menu dialog svg canvas object audio video map datalist xmp noembed noframes".split())
#: Elements that are boilerplate unless they hold most of the content.
DOUBTFUL = frozenset("form fieldset".split())
SECTIONS = frozenset("article main section div td body html".split())
CLOSES_P = frozenset("address article aside blockquote center details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SIBLING_ENDS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
#: Words in class, id or role of parts beside the article, and words that may stand with them in one name.
BOILERPLATE = frozenset(
    "nav navbar navigation menu topnav header masthead banner footer sidebar aside ad ads advert adverts advertisement adsense sponsor sponsored promo notice notices outbrain taboola "
    "cookie cookies consent gdpr popup modal alert comment comments disqus feedback respond reply replies share sharing social related recommended breadcrumb breadcrumbs pagination "
    "widget subscribe subscription newsletter signup login search form toolbar skip copyright legal complementary contentinfo".split()
)
BESIDE = frozenset("site page main top bottom left right upper lower inner outer wrap wrapper container box block area list item items section bar button buttons links link slot unit thread user reader primary secondary global".split())
PUNCTUATION = re.compile(r"[.,;:!?…、。，！？；]")

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|</?[a-zA-Z][^\s/>]*(?:[^>\"']|\"[^\"]*\"|'[^']*')*(?:>|\Z)|[^<]+|<", re.S)
_NAME = re.compile(r"</?([a-zA-Z][^\s/>]*)")
_ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
_HIDDEN = re.compile(r"\shidden(?=[\s=/>])|aria-hidden\s*=\s*[\"']?true|display\s*:\s*none", re.I)
_RAW_END = {name: re.compile(rf"</{name}\s*(?:>|\Z)", re.I) for name in RAW}


class Page:
    """Elements (parent, label, section or not) and text blocks of one page; one pass, no recursion."""

    def __init__(self, source: str):
        self.parent, self.name, self.dropped, self.path, self.doubtful = [-1], ["#root"], [False], [0], [False]
        self.paths: dict[tuple[int, str], int] = {}
        self.blocks: list[tuple[int, str]] = []
        self.linked: list[bool] = []  # of each block, whether all of it is in links
        outside = False
        stack, open_names = [0], {}
        words: list[str] = []
        owner = 0

        def flush() -> None:
            if words and (text := " ".join("".join(words).split())):
                self.blocks.append((owner, text))
                self.linked.append(not outside)
            words.clear()

        def shut(upto: int) -> None:
            while len(stack) > upto:
                open_names[self.name[stack.pop()]] -= 1

        at, size = 0, len(source)
        while at < size:
            token = _TOKEN.match(source, at)
            piece, at = token.group(), token.end()
            if piece[0] != "<" or len(piece) == 1:
                if not self.dropped[stack[-1]]:
                    if not words:
                        owner, outside = stack[-1], False
                        while owner and self.name[owner] in INLINE:
                            owner = self.parent[owner]
                    outside = outside or not open_names.get("a") and not piece.isspace()
                    words.append(html.unescape(piece))
                continue
            if piece[1] in "!?":
                continue
            name = _NAME.match(piece)[1].lower()
            if name == "br":
                words.append(" ")
                continue
            if name not in INLINE:
                flush()
            if piece[1] == "/":
                if open_names.get(name):
                    k = len(stack) - 1
                    while self.name[stack[k]] != name:
                        k -= 1
                    shut(k)
                continue
            ends = ("p",) if name in CLOSES_P else SIBLING_ENDS.get(name, ())
            for old in ends:
                if open_names.get(old):
                    k = len(stack) - 1
                    while k and self.name[stack[k]] != old and (self.name[stack[k]] in INLINE or self.name[stack[k]] in ("p", "td", "th") or old == "p" and self.name[stack[k]] not in ("table", "button", "object")):
                        k -= 1
                    if k and self.name[stack[k]] == old:
                        flush()
                        shut(k)
            if name in VOID or piece.endswith("/>") and name not in SECTIONS and name not in CLOSES_P:
                continue
            self._open(name, piece, stack, open_names)
            if name in _RAW_END:
                end = _RAW_END[name].search(source, at)
                at = end.start() if end else size
        flush()

    def _open(self, name: str, piece: str, stack: list[int], open_names: dict[str, int]) -> None:
        above = stack[-1]
        marks = [(k.lower(), (a or b or c).lower()) for k, a, b, c in _ATTRIBUTE.findall(piece)] if " " in piece or "\n" in piece or "\t" in piece else []
        gone = self.dropped[above] or name in DROPPED or bool(marks or "=" in piece or "hidden" in piece) and bool(_HIDDEN.search(piece))
        if name == "header" and "article" not in open_names and "main" not in open_names:
            gone = True
        names = [set(re.findall(r"[a-z]+", token)) for _, value in marks for token in value.split()]
        marked = any(x & BOILERPLATE and x <= BOILERPLATE | BESIDE for x in names)
        self.doubtful.append(name in DOUBTFUL or marked and name not in ("body", "html", "main", "article") and name not in INLINE)
        label = name + "".join("." + re.sub(r"\d+", "", v) for k, v in marks if k == "class")
        self.parent.append(above)
        self.name.append(name)
        self.dropped.append(gone)
        self.path.append(self.paths.setdefault((self.path[above], label), len(self.paths) + 1))
        stack.append(len(self.parent) - 1)
        open_names[name] = open_names.get(name, 0) + 1


def path_scores(page: Page, chosen: list[int], holder: np.ndarray, sigma: float = 1.0) -> np.ndarray:
    """The fused, smoothed ratio of the path of each chosen block; holder: the section that each block of the page is in."""
    path = np.array([page.path[page.blocks[i][0]] for i in chosen])
    chars = np.array([len(page.blocks[i][1]) for i in chosen], dtype=float)
    marks = np.array([len(PUNCTUATION.findall(page.blocks[i][1])) for i in chosen], dtype=float)
    _, slot = np.unique(path, return_inverse=True)
    times = np.bincount(slot)
    own, reach = holder[chosen], int(3 * sigma)

    def smooth(x: np.ndarray) -> np.ndarray:
        total, weights = x.copy(), np.ones(len(x))
        for k in range(1, min(reach, len(x) - 1) + 1):
            weight = np.exp(-0.5 * (k / sigma) ** 2) * (own[k:] == own[:-k])  # no smoothing across sections
            total[k:] += weight * x[:-k]
            total[:-k] += weight * x[k:]
            weights[k:] += weight
            weights[:-k] += weight
        return total / weights

    length = smooth((np.bincount(slot, chars) / times)[slot])
    points = smooth((np.bincount(slot, marks) / times)[slot])
    return length * (1 + points)


def content_blocks(page: Page, chosen: list[int], holder: np.ndarray, sigma: float, strictness: float) -> list[int]:
    """Of the chosen blocks those whose score reaches the threshold: the spread of all scores, or half the highest if that is less."""
    if not chosen:
        return []
    score = path_scores(page, chosen, holder, sigma)
    return [i for i, x in zip(chosen, score) if x >= min(strictness * score.std(), 0.5 * score.max())]


def mass(page: Page, content: list[int], each: bool = False) -> np.ndarray:
    """Characters (or number) of the content blocks below each element."""
    out = np.zeros(len(page.parent), dtype=np.int64)
    for i in content:
        out[page.blocks[i][0]] += 1 if each else len(page.blocks[i][1])
    for node in range(len(out) - 1, 0, -1):
        out[page.parent[node]] += out[node]
    return out


def extract(source: str | None, sigma: float = 1.0, strictness: float = 1.0) -> str:
    """Main text of one page; null, empty and text-free pages give an empty string."""
    if not source:
        return ""
    page = Page(source)
    section = [0] * len(page.parent)  # the closest section around each element, itself included
    for node in range(1, len(section)):
        section[node] = node if page.name[node] in SECTIONS else section[page.parent[node]]
    holder = np.array([section[o] for o, _ in page.blocks], dtype=np.int64)
    chosen = list(range(len(page.blocks)))
    if any(page.doubtful):
        found = mass(page, content_blocks(page, chosen, holder, sigma, strictness))
        told, above = [False] * len(page.parent), [False] * len(page.parent)  # elements in, and around, an article or main element
        for node in range(1, len(told)):
            told[node] = told[page.parent[node]] or page.name[node] in ("article", "main")
        for owner in {o for o, _ in page.blocks if told[o]}:
            while owner >= 0 and not above[owner]:
                above[owner], owner = True, page.parent[owner]
        gone = [False] * len(page.parent)
        for node in range(1, len(gone)):
            beside = above[0] and not told[node]  # if the page says where its article is, what calls itself otherwise is none
            gone[node] = gone[page.parent[node]] or page.doubtful[node] and (not above[node] if beside else 2 * found[node] < found[0])
        chosen = [i for i in chosen if not gone[page.blocks[i][0]]]
    content = content_blocks(page, chosen, holder, sigma, strictness)
    if not content:
        return ""
    inside = mass(page, content, each=True)
    top = int(np.flatnonzero(inside == len(content))[-1])  # children come after parents: the deepest that holds all
    while top and page.name[top] not in SECTIONS:
        top = page.parent[top]
    within, article = [False] * len(page.parent), [False] * len(page.parent)
    for node in range(len(within)):
        above = page.parent[node]
        within[node] = node == top or node > top and within[above]
        article[node] = node > 0 and article[above] or page.name[node] == "article" and inside[node] > 0
    menus: dict[int, int] = {}  # paths of list items that are links and no content
    chosen = [i for i in chosen if within[page.blocks[i][0]]]
    for i in set(chosen) - set(content):
        owner = page.blocks[i][0]
        if page.linked[i] and page.name[owner] == "li":
            menus[page.path[owner]] = menus.get(page.path[owner], 0) + 1
    main = set(content)

    def kept(i: int) -> bool:
        owner = page.blocks[i][0]
        if i in main or article[owner]:
            return True
        return (holder[i] == top or inside[holder[i]] > 0) and not (page.linked[i] and menus.get(page.path[owner], 0) >= 3)

    return "\n\n".join(page.blocks[i][1] for i in chosen if kept(i))


def extract_pages(pages: DataFrame, page_id: str = "page_id", url: str = "url", source: str = "html", sigma: float = 1.0, strictness: float = 1.0) -> DataFrame:
    """page_id, url, text, n_chars for every row: narrow, no shuffle, one page in memory at a time.

    A null or empty page gives an empty text; repeated rows give repeated results; an empty table gives an
    empty result; other columns are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "html"):
            texts = [extract(x, sigma, strictness) for x in batch.column(2).to_pylist()]
            yield pa.record_batch([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    rows = pick(pages, page_id=page_id, url=url, html=source)
    kinds = dict(rows.dtypes)
    return rows.mapInArrow(run, f"page_id {kinds['page_id']}, url {kinds['url']}, text string, n_chars bigint")
