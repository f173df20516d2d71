"""Main text of web pages: flat text blocks, described by shape and neighbours, classified by a decision tree.

A page is read once, in time linear in its length, by a tolerant scanner into flat blocks (runs of text between
block-level tags), each with its word count, link density and the part of the page it stands in. A block's features and
those of its two neighbours go to a small decision tree, grown here (Gini splits) on a table of blocks labelled by hand.
"""

from __future__ import annotations

import functools
import html
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kdforest.llm.common import table

#: Elements whose content is no text of the page (fixed lists of the public markup standard).
RAW = {"script", "style", "noscript", "template", "textarea", "iframe", "svg", "math", "select", "object", "canvas", "audio", "video", "noframes", "noembed", "xmp"}
INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "br", "cite", "code", "data", "del", "dfn", "em", "font", "i", "img", "ins", "kbd", "label", "mark", "q", "rp", "rt", "ruby", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
#: Elements and words in class, id and role that mark parts around an article.
AROUND = {"nav", "footer", "aside", "form", "header", "menu", "dialog", "button", "fieldset"}
AROUND_WORDS = set(
    "ad ads advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion nav navbar navigation menu breadcrumb breadcrumbs header masthead footer foot copyright sidebar side "
    "aside widget related recommended recommendations share sharing social cookie cookies consent gdpr notice alert popup modal overlay newsletter subscribe subscription signup login form search "
    "comment comments reply replies respond disqus pagination pager tags toolbar complementary contentinfo dialog reader user".split()
)
#: Parts of a name that say nothing by themselves.
NEUTRAL_WORDS = set("list box wrap wrapper container area section block bar item items inner outer group row col column panel unit slot links link posts post top bottom left right main page site global primary secondary the is-open".split())
#: Layout of a whole page, not a part of it.
LAYOUT_WORDS = re.compile(r"(?:^|(?<=\s))(?:with|has|no)-\S+")
#: Parts whose articles are comments, teasers or the like and not the page's own.
NEVER = {"nav", "footer", "aside", "menu", "dialog"}
NEVER_WORDS = re.compile(
    r"(?:^|\s)(?:ads?|adverts?|advertisement|sponsored|promo|nav|navigation|menu|footer|sidebar|aside|widget|popup|modal|overlay|pagination|complementary|contentinfo|dialog|"
    r"(?:comments?|reply|replies|respond|disqus|reader-comments|user-comments|related|recommend\w*|teasers?)(?:-\S*)?)(?=$|\s)"
)
ARTICLE_WORDS = re.compile(r"(?:^|[\s_-])(?:article|articlebody|post|entry|story|content|main|body|text)(?=$|[\s_-])")
TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)")
#: Attributes up to the end of a tag; a ">" in a quoted value doesn't end it.
ATTRIBUTES = re.compile(r"""((?:=\s*+"[^"]*+"|=\s*+'[^']*+'|[^>])*+)>""")
ATTRIBUTE = re.compile(r"""(?:^|\s)(class|id|role|hidden|aria-hidden|style)\b(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)
FEATURES = ("words", "link_density", "before_words", "before_links", "after_words", "after_links", "around", "place", "heading")


def named_part(named: str) -> int:
    """What the words in class, id and role say: 2 if a name says that this is a part around an article, 1 if a part of a name might, 0 if nothing does."""
    most = 0
    for token in named.split():
        words = [w for w in re.split(r"[_-]+", token) if w]
        said = [w in AROUND_WORDS for w in words]
        if any(said):
            most = max(most, 2 if all(ok or w in NEUTRAL_WORDS for ok, w in zip(said, words, strict=True)) else 1)
    return most


@dataclass
class Block:
    text: str
    words: int
    link_density: float
    around: int
    article: int
    heading: int


@dataclass
class _Open:
    name: str
    around: int
    article: int
    never: bool = False


@dataclass
class Scanner:
    """Flat blocks of one page."""

    blocks: list[Block] = field(default_factory=list)
    stack: list[_Open] = field(default_factory=list)
    parts: list[tuple[str, bool]] = field(default_factory=list)
    links: int = 0
    opened: Counter = field(default_factory=Counter)

    def push(self, item: _Open) -> None:
        self.stack.append(item)
        self.opened[item.name] += 1

    def cut(self, at: int) -> None:
        for item in self.stack[at:]:
            self.opened[item.name] -= 1
        del self.stack[at:]

    def close_block(self) -> None:
        text = " ".join(html.unescape("".join(p for p, _ in self.parts)).split())
        if text:
            linked = sum(len(html.unescape(p).split()) for p, a in self.parts if a)
            n = len(text.split())
            top = self.stack[-1] if self.stack else _Open("", 0, 0)
            heading = int(any(o.name in ("h1", "h2", "h3", "h4", "h5", "h6") for o in self.stack[-3:]))
            self.blocks.append(Block(text, n, min(1.0, linked / n), top.around, top.article, heading))
        self.parts = []

    def text(self, raw: str) -> None:
        if raw:
            self.parts.append((raw, self.links > 0))

    def start(self, name: str, attrs: str) -> None:
        if name == "a":
            self.links += 1
            return
        if name == "br":
            self.text(" ")
            return
        hint = {k.lower(): v.strip("\"'").lower() for k, v in ATTRIBUTE.findall(attrs)} if attrs else {}
        named = LAYOUT_WORDS.sub("", " ".join(hint.get(k, "") for k in ("class", "id", "role")))
        hidden = name not in ("html", "body") and ("hidden" in hint or hint.get("aria-hidden") == "true" or "display:none" in hint.get("style", "").replace(" ", ""))
        top = self.stack[-1] if self.stack else _Open("", 0, 0)
        if name in INLINE and not named and not hidden:
            return
        if name not in INLINE:
            self.close_block()
            if name == "p":  # an open paragraph ends where a block begins
                while self.stack and self.stack[-1].name == "p":
                    self.cut(-1)
                top = self.stack[-1] if self.stack else _Open("", 0, 0)
            if name in ("li", "tr", "td", "th", "dt", "dd", "option") and top.name == name:
                self.cut(-1)
                top = self.stack[-1] if self.stack else _Open("", 0, 0)
        elif hidden or named_part(named):
            self.close_block()
        if name in VOID:
            return
        article = top.article or name in ("article", "main") or bool(ARTICLE_WORDS.search(named))
        inside = name in ("article", "main") or "articlebody" in named
        heading_part = name == "header" and top.article  # an article's own heading
        part = name not in ("html", "body") and not inside
        never = top.never or hidden or part and not heading_part and (name in NEVER or bool(NEVER_WORDS.search(named)))
        said = max(top.around, 2 if name in AROUND and not heading_part else 0, named_part(named)) if part else 0
        self.push(_Open(name, 2 if never else said, int(article), never))

    def end(self, name: str) -> None:
        if name == "a":
            self.links = max(0, self.links - 1)
            return
        if not self.opened[name]:
            if name not in INLINE:
                self.close_block()
            return
        at = next(i for i in range(len(self.stack) - 1, -1, -1) if self.stack[i].name == name)
        if name not in INLINE or self.stack[at].around:
            self.close_block()
        self.cut(at)

    def scan(self, page: str) -> list[Block]:
        at, n, careful, unclosed = 0, len(page), True, set()
        while at < n:
            begin = page.find("<", at)
            if begin < 0:
                self.text(page[at:])
                break
            self.text(page[at:begin])
            if page.startswith("<!--", begin):
                stop = page.find("-->", begin + 4)
                at = stop + 3 if stop >= 0 else n
            elif page.startswith("<![CDATA[", begin):
                stop = page.find("]]>", begin)
                self.text(html.escape(page[begin + 9 : stop if stop >= 0 else n]))
                at = stop + 3 if stop >= 0 else n
            elif page.startswith(("<!", "<?"), begin):
                stop = page.find(">", begin)
                at = stop + 1 if stop >= 0 else n
            elif not (tag := TAG.match(page, begin)):
                self.text("<")
                at = begin + 1
            else:
                rest = ATTRIBUTES.match(page, tag.end()) if careful else None
                if rest:
                    attrs, at = rest[1], rest.end()
                else:  # quotes run to the end of the page: from here on a tag ends at its first ">"
                    careful = False
                    stop = page.find(">", tag.end())
                    attrs, at = (page[tag.end() : stop], stop + 1) if stop >= 0 else ("", n)
                    if stop < 0:
                        break  # the page ends inside a tag
                at = self.tag(page, at, bool(tag[1]), tag[2].lower(), attrs, unclosed)
        self.close_block()
        return self.blocks

    def tag(self, page: str, at: int, closing: bool, name: str, attrs: str, unclosed: set[str]) -> int:
        """Takes in a tag that ends at ``at``; where to go on. ``unclosed``: raw elements that nothing ends any more."""
        if closing:
            self.end(name)
        elif name in RAW or name in ("title", "head"):
            if name not in INLINE:
                self.close_block()
            if name != "head" and not attrs.endswith("/"):
                stop = None if name in unclosed else _ends(name).search(page, at)
                if stop:
                    return stop.end()
                unclosed.add(name)
                return len(page) if name in ("script", "style", "textarea", "title", "xmp") else at
        else:
            self.start(name, attrs)
        return at


@functools.cache
def _ends(name: str) -> re.Pattern:
    return re.compile(rf"</{name}(?![a-z0-9-])[^>]*+>", re.I)


def features(blocks: list[Block]) -> np.ndarray:
    x = np.zeros((len(blocks) + 2, 2))
    x[1:-1] = np.array([[b.words, b.link_density] for b in blocks], dtype=float).reshape(-1, 2)
    has = float(any(b.article and b.around < 2 for b in blocks))
    # place: 2 in an article, 1 in a page without one, 0 elsewhere
    own = np.array([[b.around, 2 if b.article else 1 - has, b.heading] for b in blocks], dtype=float).reshape(-1, 3)
    return np.hstack([x[1:-1], x[:-2], x[2:], own])


@dataclass
class Leaf:
    share: float


@dataclass
class Split:
    feature: int
    below: float
    low: Leaf | Split
    high: Leaf | Split


def grow(x: np.ndarray, y: np.ndarray, depth: int = 9, least: int = 1) -> Leaf | Split:
    """A classification tree: the split with the smallest weighted Gini impurity, first feature and cut of equal ones."""
    if depth == 0 or len(y) < 2 * least or y.min() == y.max():
        return Leaf(float(y.mean()))
    best = (np.inf, 0, 0.0)
    for f in range(x.shape[1]):
        values = np.unique(x[:, f])
        for cut in (values[1:] + values[:-1]) / 2:
            low = x[:, f] < cut
            if min(low.sum(), (~low).sum()) >= least:
                score = sum(s.sum() * y[s].mean() * (1 - y[s].mean()) for s in (low, ~low))
                if score < best[0] - 1e-12:
                    best = (score, f, float(cut))
    if not np.isfinite(best[0]):
        return Leaf(float(y.mean()))
    low = x[:, best[1]] < best[2]
    return Split(best[1], best[2], grow(x[low], y[low], depth - 1, least), grow(x[~low], y[~low], depth - 1, least))


def classify(tree: Leaf | Split, x: np.ndarray) -> np.ndarray:
    if isinstance(tree, Leaf):
        return np.full(len(x), tree.share >= 0.5)
    low = x[:, tree.feature] < tree.below
    out = np.empty(len(x), dtype=bool)
    out[low], out[~low] = classify(tree.low, x[low]), classify(tree.high, x[~low])
    return out


#: Pages with their blocks labelled by hand, in page order (+ text of the article, - not). {n}: n words, [n]: a link of n words.
LABELLED_PAGES = (
    ("<header><div>{2}</div>[3]</header><nav>[1][2][1]</nav><article><h1>{6}</h1><p>{60}</p><p>{3}</p><ul><li>[4]</li><li>{5}</li></ul><p>{2}[9]</p></article><aside>{30}</aside><footer>{9}[2]</footer>", "---++++++--"),
    ("<nav>[1][1][1]</nav><div class=ad>{8}</div><article><h1>{7}</h1><p>{90}</p><p>{1}</p><p>{150}</p></article><footer>{5}</footer>", "--++++-"),
    ("<div class=ad>{40}</div><main><h2>{3}</h2><p>{25}</p><p>[6]</p><blockquote>{18}</blockquote><p>{4}</p></main><div>{12}</div><div>[2]</div>", "-+++++--"),
    ("<div>{3}</div><article><p>{12}</p><table><tr><td>{2}</td><td>{1}</td></tr><tr><td>[1]</td><td>{3}</td></tr></table><p>{70}</p></article><div>{35}</div>", "-++++++-"),
    ("<article><h1>{4}</h1><p>{30}</p><aside>{14}</aside><p>{22}</p><form>{5}</form><div class=share>[1][1]</div><p>{9}</p><div id=comments><p>{40}</p><p>{12}</p></div></article><footer>[3]</footer>", "++-+--+---"),
    ("<article><p>{50}</p><div class=related-posts><h3>{2}</h3><p>[7]</p><p>{20}</p></div><p>{6}</p></article><div class=comment-list><p>{60}</p></div>", "+---+-"),
    ("<main><p>{40}</p><div class=search-results-explained><p>{20}</p><p>{35}</p></div><div class=share-it-now>[1][1]</div><p>{11}</p></main><footer>{3}</footer>", "+++-+-"),
    ("<article><p>{28}</p><div class=side-effects-box2><p>{45}</p></div><div class=user-menu-x1>[2]</div><div class=notice-of-rights><p>{17}</p></div><div class=ad-x9>[3]</div></article>", "++-+-"),
    ("<article><div class=banner-story1><p>{26}</p><p>{33}</p></div><div class=login-hint2>[2]</div><p>[5]</p></article><div class=tags-x>[1][1]</div>", "++-+-"),
    ("<div>[1][1][1][1]</div><h1>{5}</h1><p>{80}</p><p>{12}</p><p>{45}[2]</p><p>{100}</p><div>[3]</div><div>[2][2]</div>", "-+++++--"),
    ("<div>[2]</div><div>[1]</div><p>{55}</p><p>{9}</p><p>{60}[4]</p><h2>{4}</h2><p>{38}</p><div class=footer>{14}</div><div>[4]</div>", "--+++++--"),
    ("<div>{2}[3]</div><p>{16}</p><p>{24}</p><p>{7}</p><p>{31}</p><div>[5][2]</div>", "-++++-"),
    ("<ul><li>[1]</li><li>[2]</li><li>[1]</li></ul><h1>{8}</h1><p>{130}</p><p>{5}</p><p>{48}</p><ul><li>[6]</li><li>[5]</li><li>[7]</li></ul>", "---++++---"),
    ("<p>{10}</p>", "+"),
    ("<p>{3}</p>", "+"),
    ("<h1>{2}</h1><p>{6}</p>", "++"),
    ("<div class=cookie-notice>{12}</div><p>{20}</p><p>{11}</p>", "-++"),
    ("<header>{4}</header><article><header><h1>{5}</h1><p>{4}</p></header><p>{21}</p><footer>{6}</footer></article>", "-+++-"),
    ("<div class=sidebar><p>{80}</p><p>{25}</p></div><div class=post><h2>{4}</h2><p>{44}</p><p>[3]</p></div><div class=newsletter>{19}</div>", "--+++-"),
)


def labelled_blocks(pages: tuple[tuple[str, str], ...] = LABELLED_PAGES, scales: tuple[float, ...] = (1.0, 1.6, 2.5)) -> tuple[np.ndarray, np.ndarray]:
    """The labelled table: features and labels of the blocks of ``pages``, at several lengths of their texts."""
    xs, ys = [], []
    for markup, labels in pages:
        for scale in scales:

            def words(m: re.Match, scale: float = scale) -> str:
                n = int(m[1] or m[2])
                text = "w " * (n if n < 10 else round(n * scale))
                return f" {text}" if m[1] else f" <a href=x>{text}</a> "

            blocks = Scanner().scan(re.sub(r"\{(\d+)\}|\[(\d+)\]", words, markup))
            if len(blocks) != len(labels):
                raise ValueError(f"{len(blocks)} blocks, {len(labels)} labels: {markup}")
            xs.append(features(blocks))
            ys += [float(c == "+") for c in labels]
    return np.vstack(xs), np.array(ys)


@functools.cache
def default_tree() -> Leaf | Split:
    return grow(*labelled_blocks())


def main_text(page: str | None, tree: Leaf | Split | None = None) -> str:
    blocks = Scanner().scan(page or "")
    if not blocks:
        return ""
    keep = classify(tree or default_tree(), features(blocks))
    return "\n".join(b.text for b, k in zip(blocks, keep, strict=True) if k)


def extract(pages: DataFrame, tree: Leaf | Split | None = None, html_col: str = "html") -> DataFrame:
    """``pages`` with column text: the main text, blocks joined by one line feed.

    White space inside a block is one space and references are decoded. A null or empty page, and one without
    text, give "". Other columns, also null ones, stay as they are; a column named text is replaced.
    """
    tree = tree or default_tree()
    rest = pages.drop("text") if html_col != "text" else pages
    schema = rest.drop("text").withColumn("text", F.lit("")).schema

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            text = pa.array([main_text(x.as_py(), tree) for x in b.column(html_col)], pa.string())
            names = [n for n in b.schema.names if n != "text"]
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in names), text], [*names, "text"])

    return rest.mapInArrow(work, schema)


def op5_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page; see ``extract``."""
    slim = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    # the markup itself stays in the worker
    tree = default_tree()

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([main_text(x.as_py(), tree) for x in b.column(2)], pa.string())], ["page_id", "url", "text"])

    found = slim.mapInArrow(work, "page_id long, url string, text string")
    return found.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
