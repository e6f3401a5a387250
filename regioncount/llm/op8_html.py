"""Main text of web pages: gradient-boosted trees over DOM nodes, then hierarchical decoding.

Every element gets features (subtree text and tag density, link share, attribute tokens, depth, sibling statistics,
position) and two probabilities from trees: that it lies in the article, and that it only contains it (an ancestor of
article nodes, such as body). What remains is boilerplate. A dynamic programme over the tree picks the likeliest
state of all nodes together under two rules: below boilerplate all is boilerplate, and below the article only article
or boilerplate (inline elements in it are article). So no node contradicts an ancestor or a descendant. Texts of article nodes are the result.

The trees are trained here on generated pages of many layouts with known article nodes (`n_pages`, a documented
bound). Scripts, styles, head, forms, templates and their like are never text.

A block is the text between two block-level boundaries; a line break inside a block counts as white space. Defined
cases: null or empty html gives the empty text; plain wrappers are taken out first, so nesting without meaning does not count; unclosed, stray and misnested tags are repaired as browsers commonly
do; text outside any element is judged with the root; repeated rows are extracted one by one; very long pages are read
whole, without recursion; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import math
import random
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from regioncount.llm import gbt

#: Fixed lists of HTML: elements without content, block elements, elements whose text is never shown as text.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
HIDDEN = frozenset("script style head title noscript template form textarea select option button input label svg iframe object canvas audio video math datalist".split())
#: A start tag of these closes an open element of those, up to a border.
CLOSES = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
#: Words of class and id attributes that speak for and against the article.
GOOD = frozenset("article body content entry main page post story text prose chapter".split())
BAD = frozenset("ad ads advert advertisement banner breadcrumb breadcrumbs comment comments consent cookie copyright disclaimer discussion disqus feedback footer form header login menu modal nav navbar navigation newsletter notice pager pagination popup promo promoted related replies reply respond search share sharing sidebar signup skip social sponsor sponsored subscribe tags toolbar top widget".split())
#: Elements that may wrap another without a meaning of their own.
WRAPPERS = frozenset(("div", "section", "center"))
INLINE_WRAPPERS = frozenset(("span", "font"))
#: Deeper nodes count as this deep.
DEEPEST = 8
CONTAINER, ARTICLE, BOILER = 0, 1, 2
_WORD = re.compile(r"[a-z]+")


@dataclass
class Page:
    tag: list[str] = field(default_factory=lambda: ["#root"])
    words: list[frozenset] = field(default_factory=lambda: [frozenset()])
    parent: list[int] = field(default_factory=lambda: [-1])
    #: In page order: (node, text), or (node, None) at a block boundary.
    runs: list[tuple[int, str | None]] = field(default_factory=list)


class _Builder(HTMLParser):
    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.page, self.open = Page(), [0]
        #: Open elements by tag, so that a stray end tag costs no search.
        self.count: dict[str, int] = {}

    def _cut(self, k: int) -> None:
        for x in self.open[k:]:
            self.count[self.page.tag[x]] -= 1
        del self.open[k:]

    def handle_starttag(self, tag, attrs):
        p = self.page
        if tag in BLOCK and tag != "html" and tag != "body":
            self._close({"p"}, {"table", "td", "th", "button"})
        if tag in CLOSES:
            self._close(*CLOSES[tag])
        node = len(p.tag)
        p.tag.append(tag)
        p.words.append(frozenset(w for k, v in attrs if v and k in ("class", "id", "role") for w in _WORD.findall(v.lower())))
        p.parent.append(self.open[-1])
        if tag in BLOCK:
            p.runs.append((node, None))
        elif tag == "br":
            p.runs.append((self.open[-1], " "))
        if tag not in VOID:
            self.open.append(node)
            self.count[tag] = self.count.get(tag, 0) + 1

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)

    def _close(self, tags, borders):
        if not any(self.count.get(t) for t in tags):
            return
        for k in range(len(self.open) - 1, 0, -1):
            t = self.page.tag[self.open[k]]
            if t in tags:
                self._cut(k)
                self.page.runs.append((self.open[-1], None))
                return
            if t in borders:
                return

    def handle_endtag(self, tag):
        if not self.count.get(tag):
            return
        for k in range(len(self.open) - 1, 0, -1):
            if self.page.tag[self.open[k]] == tag:
                if any(self.page.tag[x] in BLOCK for x in self.open[k:]):
                    self.page.runs.append((self.open[k - 1], None))
                self._cut(k)
                return
            if self.page.tag[self.open[k]] in ("td", "th", "table") and tag not in BLOCK:
                return

    def handle_data(self, data):
        self.page.runs.append((self.open[-1], data))


def plain_wrappers(p: Page) -> list[bool]:
    """Whether each node adds nothing to its only child element that has text: no text of its own and no attribute
    word that speaks for or against the article. A block wraps a block, an inline element any."""
    n = len(p.tag)
    children, texts, below = [0] * n, [False] * n, [False] * n
    only = [0] * n
    for node, text in p.runs:
        if text and not text.isspace():
            texts[node] = below[node] = True
    for k in range(n - 1, 0, -1):
        if below[k]:
            below[p.parent[k]] = True
            children[p.parent[k]] += 1
            only[p.parent[k]] = k
    wraps = [p.tag[k] in INLINE_WRAPPERS or p.tag[k] in WRAPPERS and p.tag[only[k]] in BLOCK for k in range(n)]
    return [k > 0 and wraps[k] and children[k] == 1 and not texts[k] and not p.words[k] & (GOOD | BAD) for k in range(n)]


def collapse(p: Page, gone: list[bool]) -> tuple[Page, list[int]]:
    """The page without these nodes, whose children and block boundaries go to their parents, and the nodes that stay.

    So the depth of nesting alone decides nothing: a text below thousands of plain wrappers is judged as below none.
    """
    if not any(gone):
        return p, list(range(len(p.tag)))
    at, stay = [0] * len(gone), []
    for k, out in enumerate(gone):
        if out:
            at[k] = at[p.parent[k]]
        else:
            at[k] = len(stay)
            stay.append(k)
    page = Page([p.tag[k] for k in stay], [p.words[k] for k in stay], [at[p.parent[k]] if k else -1 for k in stay])
    page.runs = [(at[node], text) for node, text in p.runs]
    return page, stay


def parse(source: str) -> Page:
    b = _Builder()
    b.feed(source)
    b.close()
    return collapse(b.page, plain_wrappers(b.page))[0]


FEATURES = ("depth", "nodes", "chars", "own_chars", "density", "link_share", "paragraphs", "stops", "words_per_run", "start", "end", "of_parent", "of_page", "place", "siblings", "same_tag", "good", "bad", "good_above", "bad_above", "is_p", "is_div", "is_list", "is_heading", "is_inline", "is_article", "is_boiler_tag", "is_table", "in_article_tag", "in_boiler_tag", "hidden", "is_root", "article_below", "headings", "before_article", "after_article")
_ARTICLE_TAGS, _BOILER_TAGS = frozenset(("article", "main")), frozenset(("nav", "footer", "header", "aside", "form", "menu", "dialog"))


def features(p: Page) -> np.ndarray:
    n = len(p.tag)
    own, links, runs, stops = [0] * n, [0] * n, [0] * n, [0] * n
    in_link, hidden = [False] * n, [False] * n
    depth, good_above, bad_above, in_art, in_boil = [0] * n, [0] * n, [0] * n, [0] * n, [0] * n
    children, rank, kinds = [0] * n, [0] * n, {}
    for k in range(n):
        t, up = p.tag[k], p.parent[k]
        if up >= 0:
            depth[k] = min(DEEPEST, depth[up] + 1)
            good_above[k] = good_above[up] + len(p.words[up] & GOOD)
            bad_above[k] = bad_above[up] + len(p.words[up] & BAD)
            in_art[k] = in_art[up] + (p.tag[up] in _ARTICLE_TAGS)
            in_boil[k] = in_boil[up] + (p.tag[up] in _BOILER_TAGS)
            rank[k] = children[up]
            children[up] += 1
            kinds[up, t] = kinds.get((up, t), 0) + 1
            in_link[k], hidden[k] = in_link[up] or t == "a", hidden[up] or t in HIDDEN
    first, last, at = [-1] * n, [0] * n, 0
    for node, text in p.runs:
        if text is None or hidden[node]:
            continue
        size = len(text.strip())
        if size:
            own[node] += size
            links[node] += size * in_link[node]
            runs[node] += 1
            stops[node] += sum(map(text.count, ".,;!?"))
            if first[node] < 0:
                first[node] = at
            at += size
            last[node] = at
    chars, nodes, all_links, all_runs, all_stops = own[:], [1] * n, links[:], runs[:], stops[:]
    paragraphs, headings, art_below = [0] * n, [0] * n, [0] * n
    for k in range(n - 1, 0, -1):
        up = p.parent[k]
        for v in (chars, nodes, all_links, all_runs, all_stops, paragraphs, headings, art_below):
            v[up] += v[k]
        t = p.tag[k]
        paragraphs[up] += t == "p"
        headings[up] += t in ("h1", "h2", "h3")
        art_below[up] += t in _ARTICLE_TAGS
        if first[k] >= 0:
            first[up] = first[k] if first[up] < 0 else min(first[up], first[k])
            last[up] = max(last[up], last[k])
    total = max(1, at)
    art = next((k for k in range(n) if p.tag[k] in _ARTICLE_TAGS and chars[k]), -1)
    out = np.zeros((n, len(FEATURES)))
    for k in range(n):
        t, up = p.tag[k], max(0, p.parent[k])
        begin = first[k] if first[k] >= 0 else 0
        out[k] = (
            depth[k], math.log1p(nodes[k]), math.log1p(chars[k]), math.log1p(own[k]), nodes[k] / (1 + chars[k]), all_links[k] / max(1, chars[k]), paragraphs[k], all_stops[k] / (1 + chars[k]) * 100, chars[k] / max(1, all_runs[k]),
            begin / total, last[k] / total, chars[k] / max(1, chars[up]), chars[k] / total, rank[k] / max(1, children[up]), children[up], kinds.get((up, t), 1), len(p.words[k] & GOOD), len(p.words[k] & BAD), good_above[k], bad_above[k],
            t == "p", t in ("div", "section"), t in ("ul", "ol", "li", "dl", "dt", "dd"), t in ("h1", "h2", "h3", "h4", "h5", "h6"), t not in BLOCK, t in _ARTICLE_TAGS, t in _BOILER_TAGS, t in ("table", "tr", "td", "th", "tbody"), in_art[k], in_boil[k], hidden[k], k == 0 or t in ("html", "body"), art_below[k], headings[k],
            art >= 0 and last[k] <= first[art], art >= 0 and begin >= last[art],
        )
    return out


def decode(p: Page, article: np.ndarray, container: np.ndarray) -> list[int]:
    """States of all nodes: the likeliest under the rules of the module's text. Parents precede their children."""
    eps = 1e-6
    n = len(p.tag)
    logs = [[math.log(max(container[k], eps)), math.log(max(article[k], eps)), math.log(max(1 - article[k] - container[k], eps))] for k in range(n)]
    for k in range(n):
        if p.tag[k] in HIDDEN:
            logs[k] = [-50.0, -50.0, 0.0]
    inline = [t not in BLOCK and t not in HIDDEN for t in p.tag]
    best = [list(x) for x in logs]
    for k in range(n - 1, 0, -1):
        b, up = best[k], best[p.parent[k]]
        up[CONTAINER] += max(b)
        up[ARTICLE] += b[ARTICLE] if inline[k] else max(b[ARTICLE], b[BOILER])
        up[BOILER] += b[BOILER]
    state = [0] * n
    state[0] = max((CONTAINER, ARTICLE, BOILER), key=lambda s: best[0][s])
    for k in range(1, n):
        up = state[p.parent[k]]
        allowed = (CONTAINER, ARTICLE, BOILER) if up == CONTAINER else (ARTICLE,) if up == ARTICLE and inline[k] else (ARTICLE, BOILER) if up == ARTICLE else (BOILER,)
        state[k] = max(allowed, key=lambda s: best[k][s])
    return state


def assemble(p: Page, state: list[int]) -> str:
    blocks, current = [], []
    for node, text in p.runs:
        if text is None:
            blocks.append(current)
            current = []
        elif state[node] == ARTICLE:
            current.append(text)
    texts = (" ".join("".join(b).split()) for b in [*blocks, current])
    return "\n".join(t for t in texts if t)


# ---------------------------------------------------------------- generated training pages
def make_page(rng: random.Random) -> str:
    """A page of a random layout; elements of the article carry the attribute data-m."""
    word = lambda: "".join(rng.choice("abcdefghijklmnoprstuvwy") for _ in range(rng.randint(2, 10)))
    sentence = lambda a=4, b=18: (" ".join(word() for _ in range(rng.randint(a, b))) + rng.choice(".,.!?")).capitalize()
    prose = lambda a=1, b=6: " ".join(sentence() for _ in range(rng.randint(a, b)))
    links = lambda k: "".join(f'<li><a href="/{word()}">{word()}</a></li>' for _ in range(k))
    choose, odds = rng.choice, lambda x: rng.random() < x

    def body_block() -> str:
        kind = rng.random()
        if kind < 0.62:
            t = prose(1, choose([1, 3, 8])) if odds(0.95) else (word() + choose([" ", ", "])) * choose([20, 300, 2500])
            if odds(0.15):
                t = f"<b data-m>{t}<br>" if odds(0.7) else f"<b data-m>{t}</b>"
            elif odds(0.2):
                t += f' <a data-m href="/x">{word()} {word()}</a> <em data-m>{sentence(1, 4)}</em>'
            return f"<p data-m>{t}" + ("</p>" if odds(0.85) else "")
        if kind < 0.72:
            return f"<h2 data-m>{sentence(2, 6)}</h2>"
        if kind < 0.8:
            return "<ul data-m>" + "".join(f"<li data-m>{prose(1, 2)}</li>" for _ in range(rng.randint(2, 5))) + "</ul>"
        if kind < 0.86:
            return f"<blockquote data-m><p data-m>{prose(1, 3)}</p></blockquote>"
        if kind < 0.91:
            return "<table data-m>" + "".join(f"<tr data-m><td data-m>{word()}</td><td data-m>{rng.randint(1, 999)}</td></tr>" for _ in range(3)) + "</table>"
        if kind < 0.95:
            return f"<pre data-m>{word()} = {word()};\n{word()}()</pre>"
        return choose([f'<div class="{choose(["ad", "advert", "promo", "sponsored", "banner"])}">{prose(1, 2)}</div>', f'<aside class="{choose(["related", "share", "newsletter"])}"><p>{prose(1, 2)}</p></aside>', f"<form><label>{word()}</label><input><button>{word()}</button></form>", f'<figure data-m><img src="x"><figcaption data-m>{sentence()}</figcaption></figure>'])

    heading = f"<h1 data-m>{sentence(2, 14)}</h1>" if odds(0.9) else ""
    inner = heading + "".join(body_block() for _ in range(choose([0, 1, 2, 4, 8, 20])))
    if inner == "":
        inner = f"<p data-m>{word()}</p>"
    if odds(0.14):  # a fragment: all of it is article, the root too
        return choose([prose(1, 4), word(), f"<p data-m>{word()}<p data-m>{word()}"]) if odds(0.5) else inner if odds(0.7) else f"<div data-m>{inner}</div>"
    if odds(0.2):
        inner = f"<div data-m>{inner}</div>"
    main = inner if odds(0.06) else choose([f"<article data-m>{inner}</article>"] * 5 + [f"<div data-m>{inner}</div>"] * 2 + [f"<main data-m>{inner}</main>", f'<div data-m class="{choose(["content", "post", "entry-content", "article-body", "story"])}">{inner}</div>', f'<div data-m id="{choose(["content", "main", "text"])}">{inner}</div>', f"<main><article data-m>{inner}</article></main>"])
    if odds(0.15):
        main = f'<div class="{choose(["wrapper", "container", "row", "col"])}">{main}</div>'
    if odds(0.12):  # nested wrappers that do not collapse, each beside an empty element
        for _ in range(rng.randint(1, 12)):
            main = f"<div>{choose(['<hr>', '<div></div>', '<img src=x>'])}{main}</div>"
    top, bottom = [], []
    if odds(0.85):
        top.append(f"<nav><ul>{links(rng.randint(3, 9))}</ul></nav>" if odds(0.8) else f'<div class="menu"><ul>{links(6)}</ul></div>')
    if odds(0.35):
        top.append(f"<header><h2>{word()} {word()}</h2><p>{sentence()}</p></header>" if odds(0.6) else f'<div id="header"><h1>{word()}</h1></div>')
    if odds(0.6):
        top.append(f'<div class="{choose(["ad", "ad", "ads", "advert", "banner", "promo"])}">{prose(1, 3)}</div>')
    if odds(0.25):
        top.append(f'<div class="{choose(["cookie", "cookie-notice", "notice", "consent"])}"><p>{prose(1, 3)}</p><button>{word()}</button></div>')
    if odds(0.25):
        (top if odds(0.3) else bottom).append(f'<{(t := choose(["aside", "div"]))} class="sidebar"><h3>{word()}</h3><p>{prose(1, 3)}</p><ul>{links(4)}</ul></{t}>')
    if odds(0.3):
        comments = "".join(f'<{(t := choose(["div", "li", "article"]))} class="comment"><b>{word()}</b><p>{prose(1, 5)}</p></{t}>' for _ in range(rng.randint(1, 8)))
        bottom.append(choose([f'<section id="comments"><h3>{word()}</h3>{comments}</section>', f'<div class="comments">{comments}</div>', f'<section class="comments"><ol>{comments}</ol></section>']))
    if odds(0.25):
        bottom.append(f"<form><p>{sentence()}</p><label>{word()}</label><input><button>{word()}</button></form>")
    if odds(0.2):
        bottom.append(f'<div class="{choose(["related", "share", "tags", "newsletter", "pagination"])}"><h3>{word()}</h3><ul>{links(4)}</ul></div>')
    if odds(0.85):
        bottom.append(f"<footer>&copy; {word()}.example &middot; {prose(1, 4)}" + ("</footer>" if odds(0.8) else "") if odds(0.8) else f'<div class="footer"><p>{prose(1, 3)}</p></div>')
    rng.shuffle(top)
    head = f'<!DOCTYPE html><html><head><meta charset="utf-8"><title>{sentence()}</title><style>p{{margin:0}}</style><script>var t="</p>";</script></head>'
    return f"{head}<body>{''.join(top)}<!-- {word()} -->{main}{''.join(bottom)}" + ("</body></html>" if odds(0.9) else "")


def labelled(source: str) -> tuple[Page, np.ndarray]:
    """Page without the marks, and the state of each node."""

    class Marked(_Builder):
        marks: list[bool]

        def handle_starttag(self, tag, attrs):
            self.marks.append(any(k == "data-m" for k, _ in attrs))
            super().handle_starttag(tag, attrs)

    b = Marked()
    b.marks = [not source.startswith("<!DOCTYPE")]
    b.feed(source)
    b.close()
    state = np.full(len(b.marks), BOILER)
    for k in range(len(b.marks) - 1, -1, -1):
        if b.marks[k]:
            state[k] = ARTICLE
        up = b.page.parent[k]
        if up >= 0 and state[k] in (ARTICLE, CONTAINER) and not b.marks[up]:
            state[up] = CONTAINER
    page, stay = collapse(b.page, plain_wrappers(b.page))
    return page, state[stay]


@dataclass
class Extractor:
    article: gbt.Trees
    container: gbt.Trees

    def texts(self, sources: list[str | None], batch_nodes: int = 4096) -> list[str]:
        out: list[str] = []
        held: list[tuple[Page, np.ndarray]] = []

        def flush() -> None:
            if held:
                x = np.concatenate([f for _, f in held])
                a, c = self.article.probabilities(x), self.container.probabilities(x)
                at = 0
                for p, f in held:
                    out.append(assemble(p, decode(p, a[at : at + len(f)], c[at : at + len(f)])))
                    at += len(f)
                held.clear()

        size = 0
        for s in sources:
            p = parse(s or "")
            f = features(p)
            held.append((p, f))
            size += len(f)
            if size >= batch_nodes:
                flush()
                size = 0
        flush()
        return out


def train(n_pages: int = 1000, seed: int = 5) -> Extractor:
    rng = random.Random(seed)
    x, y = [], []
    for _ in range(n_pages):
        p, state = labelled(make_page(rng))
        x.append(features(p))
        y.append(state)
    x, y = np.concatenate(x), np.concatenate(y)
    return Extractor(gbt.fit(x, (y == ARTICLE).astype(float), trees=40, depth=4), gbt.fit(x, (y == CONTAINER).astype(float), trees=15, depth=3))


def extract(pages: DataFrame, model: Extractor | None = None) -> DataFrame:
    """(page_id, url, text, n_chars) of every page."""
    shared = pages.sparkSession.sparkContext.broadcast(model or train())
    pages = pages.select("page_id", "url", "html")
    kind = pages.schema["page_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = shared.value.texts(batch.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.mapInArrow(run, f"page_id {kind}, url string, text string, n_chars long")
