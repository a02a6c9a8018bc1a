"""Main text of web pages by tree scoring.

A page is read once into a tree. Parts that are never article text (menus, headers, footers, sidebars, notices, adverts, forms,
scripts, styles, reader comments; told by element, role, or words of class and id) are set aside. Every paragraph then gives its
parent points for its length and its commas, the grandparent half, the next ones less; a container's points are discounted by the
share of its text that stands in links. The best container is kept whole, with those siblings that read like article text.

Blocks are what stands between block-level borders: character references decoded, white space turned into one blank, trimmed;
empty blocks vanish, the others are joined by two line ends in page order. Formulas stay, their annotations don't. A part of an article
that is only told by a word such as `alert` or `related` is judged by what it holds: prose stays, lists of links and short remarks go.
Null and empty pages give the empty string, and so
does a page that is nothing but set-aside parts. With equal points the container that comes first wins. Pages of any depth or
length are read without recursion and in time that grows with their length, however broken their markup is; rows are mapped one by one, so repeated rows and extra columns need no care.
"""

from __future__ import annotations

import html
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import arrow_map

#: Fixed values of the markup language.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIPPED = frozenset("script style textarea title noscript iframe template xmp noembed noframes svg annotation annotation-xml select object audio video canvas".split())
BLOCKS = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 "
    "header hgroup hr html li main menu nav ol p pre search section summary table tbody td tfoot th thead tr ul caption legend".split()
)
CLOSES_P = BLOCKS - frozenset("body html li dd dt td th tr tbody thead tfoot caption legend".split()) | {"p"}
#: A start tag closes these open elements, up to the given borders.
IMPLIED = {
    "li": ({"li"}, {"ul", "ol", "menu"}),
    "dt": ({"dt", "dd"}, {"dl"}),
    "dd": ({"dt", "dd"}, {"dl"}),
    "tr": ({"tr", "td", "th"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}),
    "th": ({"td", "th"}, {"tr", "table"}),
    "tbody": ({"tbody", "thead", "tfoot", "tr", "td", "th"}, {"table"}),
    "tfoot": ({"tbody", "thead", "tr", "td", "th"}, {"table"}),
    "option": ({"option"}, {"select"}),
}

#: Parts that are never the article.
ASIDE_TAGS = frozenset("nav header footer aside form button dialog menu search head label input output progress meter".split())
ASIDE_ROLES = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert menu menubar toolbar form".split())
LAYOUT_WORDS = frozenset("sidebar sidebars nav navbar navigation menu menus footer foot masthead topbar header widget widgets banner banners overlay notice".split())  # also said of what holds the article
ASIDE_WORDS = LAYOUT_WORDS | frozenset(
    "ad ads adv advert adverts advertisement advertising adsense sponsor sponsored sponsors promo promos promotion promoted "
    "breadcrumb breadcrumbs comment comments commentlist respond replies reply disqus discussion cookie cookies consent gdpr "
    "notices notification alert popup modal lightbox newsletter subscribe subscription signup login share sharing social related recommended "
    "recommendations pagination pager skip toolbar outbrain taboola".split()
)
#: Words that are also said of parts of an article, which are then judged by what they hold.
SOFT_WORDS = frozenset("alert notification notices promo promos promotion promoted share sharing social related recommended recommendations discussion popup modal lightbox skip toolbar sponsor sponsored sponsors".split())
LIKELY_WORDS = frozenset("article body content entry main page post text blog story".split())
START = {"article": 25, "main": 20, "div": 5, "section": 3, "pre": 3, "td": 3, "blockquote": 3, "address": -3, "ol": -3, "ul": -3, "dl": -3, "dd": -3, "dt": -3, "li": -3, "form": -3, "th": -5} | {f"h{i}": -5 for i in range(1, 7)}
PARAGRAPHS = frozenset("p pre td blockquote li dd figcaption".split())
PROSE = frozenset("p pre blockquote ul ol dl table figure h1 h2 h3 h4 h5 h6".split())

_NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_STOP = re.compile(r"[>\"']")
_ATTR = re.compile(r"([a-zA-Z_:][-\w:.]*)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_WORD = re.compile(r"[a-z0-9]+")
_HUMP = re.compile(r"(?<=[a-z])(?=[A-Z])")


def _attributes(raw: str) -> dict[str, str]:
    found = {}
    for m in _ATTR.finditer(raw):
        found.setdefault(m[1].lower(), html.unescape(m[2] or m[3] or m[4] or ""))
    return found


def _words(value: str) -> set[str]:
    return set(_WORD.findall(_HUMP.sub(" ", value).lower()))


class Tags:
    """Finds the ends of tags. A quote hides what ends a tag; a quote that nothing closes is taken as a mark. Where quotes pair up so that no
    tag ends before the page does, the next end is taken; after LOST such cases the page's quotes are no longer looked at, so that a page
    is never read over and over."""

    LOST = 16

    def __init__(self, source: str):
        self.source, self.lost = source, 0
        self.last = {c: source.rfind(c) for c in "\"'>"}

    def end(self, at: int) -> int:
        """Where the tag whose name ends at `at` has its closing mark; -1 without any."""
        source = self.source
        if at > self.last[">"]:
            return -1
        if self.lost < self.LOST:
            k = at
            while (m := _STOP.search(source, k)) is not None:
                if m[0] == ">":
                    return m.start()
                k = m.end() if m.start() >= self.last[m[0]] else source.index(m[0], m.end()) + 1
            self.lost += 1
        return source.find(">", at)


class Page:
    """Elements in page order (tag, parent, end of their subtree) and text runs (element, block, text)."""

    def __init__(self, source: str):
        self.tag: list[str] = ["#root"]
        self.parent: list[int] = [-1]
        self.aside: list[int] = [0]  # 1: by its element, role, being hidden, class or id; 2: by a word of layout in its class or id; 3: by a soft word
        self.weight: list[int] = [0]
        self.stop: list[int] = [0]
        self.runs: list[tuple[int, int, str]] = []
        self._read(source)

    def _open(self, tag: str, raw: str, stack: list[int]) -> int:
        aside = weight = 0
        if tag in ASIDE_TAGS:
            aside = 1
        if raw and not raw.isspace():
            a = _attributes(raw)
            if a.get("role", "").lower() in ASIDE_ROLES or "hidden" in a or a.get("aria-hidden", "").lower() == "true" or "display:none" in a.get("style", "").replace(" ", "").lower():
                aside = 1
            names = _words(f"{a.get('class', '')} {a.get('id', '')}")
            if names:
                if names & ASIDE_WORDS and tag not in ("html", "body", "article", "main"):
                    told = names & ASIDE_WORDS
                    aside = aside or (2 if told <= LAYOUT_WORDS else 3 if told <= SOFT_WORDS else 1)
                weight = 25 * bool(names & LIKELY_WORDS) - 25 * bool(names & ASIDE_WORDS)
        i = len(self.tag)
        self.tag.append(tag)
        self.parent.append(stack[-1])
        self.aside.append(aside)
        self.weight.append(weight)
        self.stop.append(0)
        stack.append(i)
        return i

    def _read(self, source: str) -> None:
        stack, block, at, n = [0], 0, 0, len(source)
        tags, stop, runs = self.tag, self.stop, self.runs
        ends = Tags(source)
        opened: Counter[str] = Counter()  # how many elements of a name are open, so that none is looked for in vain
        comments, marks = source.rfind("-->"), source.rfind(">")

        def close(depth: int) -> None:
            while len(stack) > depth:
                opened[tags[stack[-1]]] -= 1
                stop[stack.pop()] = len(tags)

        while at < n:
            lt = source.find("<", at)
            if lt < 0:
                lt = n
            if lt > at:
                runs.append((stack[-1], block, source[at:lt]))
            if lt == n:
                break
            if source.startswith("<!--", lt):
                end = source.find("-->", lt + 4) if comments >= lt + 4 else -1
                at = n if end < 0 else end + 3
                continue
            if source.startswith(("<!", "<?"), lt):
                end = source.find(">", lt) if marks > lt else -1
                at = n if end < 0 else end + 1
                continue
            m = _NAME.match(source, lt)
            end = ends.end(m.end()) if m is not None else -1
            if end < 0:
                runs.append((stack[-1], block, "<"))
                at = lt + 1
                continue
            at, tag, inner = end + 1, m[2].lower(), source[m.end() : end]
            if m[1]:
                if opened[tag]:
                    k = len(stack) - 1
                    while tags[stack[k]] != tag:
                        k -= 1
                    close(k)
                block += tag in BLOCKS
                continue
            if tag in SKIPPED:
                if not inner.endswith("/"):
                    end = re.compile(rf"</{re.escape(tag)}(?=[\s/>])[^>]*>", re.IGNORECASE).search(source, at)
                    at = end.end() if end else n
                continue
            if tag == "br" or tag == "wbr":
                if tag == "br":
                    runs.append((stack[-1], block, " "))
                continue
            if tag in CLOSES_P and opened["p"]:
                for k in range(len(stack) - 1, 0, -1):
                    t = tags[stack[k]]
                    if t == "p":
                        close(k)
                        break
                    if t in BLOCKS:
                        break
            if tag in IMPLIED:
                closed, borders = IMPLIED[tag]
                for k in range(len(stack) - 1, 0, -1) if any(map(opened.__getitem__, closed)) else ():
                    t = tags[stack[k]]
                    if t in borders:
                        break
                    if t in closed:
                        close(k)
                        if tag not in ("tr", "tbody", "tfoot"):
                            break
            block += tag in BLOCKS
            if tag in VOID:
                continue
            self._open(tag, inner, stack)
            opened[tag] += 1
        close(0)

    def text(self) -> str:
        tags, parent, n = self.tag, self.parent, len(self.tag)
        # a part told by a word of layout is no aside if it holds the article itself, or most of the page's text
        sure = [False] * n
        for i in range(1, n):
            sure[i] = sure[parent[i]] or self.aside[i] == 1
        linked, within = [False] * n, [False] * n  # in a link, in an article
        for i in range(1, n):
            linked[i] = linked[parent[i]] or tags[i] == "a"
            within[i] = within[parent[i]] or tags[parent[i]] in ("article", "main")
        mass, by_link, sentences = [0] * n, [0] * n, [0] * n
        for node, _, run in self.runs:
            if not sure[node]:
                k = len(run.strip())
                mass[node] += k
                by_link[node] += k * linked[node]
                sentences[node] += run.count(".") + run.count("!") + run.count("?") + run.count("。")
        holds = [False] * n
        for i in range(n - 1, 0, -1):
            mass[parent[i]] += mass[i]
            by_link[parent[i]] += by_link[i]
            sentences[parent[i]] += sentences[i]
            if not sure[i] and (holds[i] or tags[i] in ("article", "main") or self.weight[i] > 0):
                holds[parent[i]] = True
        for i in range(1, n):
            holds[i] = holds[i] or 2 * mass[i] > mass[0]
        gone = [False] * n
        for i in range(1, n):
            prose = within[i] and mass[i] >= 100 and 3 * by_link[i] < mass[i] and sentences[i] > 0
            gone[i] = gone[parent[i]] or self.aside[i] == 1 or (self.aside[i] == 2 and not holds[i]) or (self.aside[i] == 3 and not prose)
        blocks: dict[int, list[tuple[int, str]]] = {}
        for node, block, run in self.runs:
            if not gone[node]:
                blocks.setdefault(block, []).append((node, run))
        size, links = [0] * n, [0] * n
        done: list[tuple[int, str]] = []  # element and text of each block
        block_of = [0] * n  # the nearest block element
        for i in range(1, n):
            block_of[i] = i if tags[i] in BLOCKS else block_of[parent[i]]
        for runs in blocks.values():
            whole = " ".join(html.unescape("".join([r for _, r in runs])).split())
            if not whole:
                continue
            node = next(x for x, r in runs if not r.isspace())
            for x, r in runs:
                k = len(r.strip())
                size[x] += k
                if linked[x]:
                    links[x] += k
            done.append((block_of[node], whole))
        if not done:
            return ""
        score: dict[int, float] = {}
        for node, whole in done:
            if len(whole) < 25:
                continue
            points = 1 + whole.count(",") + whole.count("，") + min(len(whole) // 100, 3)
            x, depth = (parent[node] if tags[node] in PARAGRAPHS and parent[node] > 0 else node), 1
            while x > 0 and depth <= 5:
                score[x] = score.get(x, START.get(tags[x], 0) + self.weight[x]) + points / (1 if depth == 1 else 2 if depth == 2 else 3 * (depth - 1))
                x, depth = parent[x], depth + 1
        for i in range(n - 1, 0, -1):
            size[parent[i]] += size[i]
            links[parent[i]] += links[i]
        best, top = 0, 0.0
        for i in sorted(score):
            s = score[i] * (1 - links[i] / max(size[i], 1))
            if tags[i] not in ("html", "body") or not best:
                if s > top or not best:
                    best, top = i, s
        if not best:  # only short lines: the article if there is one
            best = next((i for i in range(n) if tags[i] in ("article", "main") and not gone[i] and size[i]), 0)
        x = best
        while x > 0:  # inside an article, all of it
            if tags[x] in ("article", "main"):
                best = x
                if tags[x] == "article":
                    break
            x = parent[x]
        kept = [best]
        if best and tags[best] not in ("article", "main", "body", "html"):
            up = parent[best]
            for i in range(up + 1, self.stop[up]):
                if parent[i] != up or i == best or gone[i] or not size[i]:
                    continue
                density = links[i] / size[i]
                good = score.get(i, 0) * (1 - density) >= max(10, 0.2 * top) or (density < 0.5 if tags[i] in PROSE else density < 0.25 and size[i] > 80)
                if good:
                    kept.append(i)
            if any(node == up for node, _ in done) and tags[up] not in ("body", "html", "#root"):
                kept = [up]
        inside = bytearray(n)
        for i in kept:
            inside[i : self.stop[i]] = b"\1" * (self.stop[i] - i)
        return "\n\n".join([whole for node, whole in done if inside[node]])


def extract_text(source: str | None) -> str:
    return Page(source).text() if source else ""


def extract(pages: DataFrame, id_column: str = "page_id", url: str = "url", source: str = "html") -> DataFrame:
    """(id, url, text, n_chars) of every page."""
    kinds = dict(pages.dtypes)

    def make():
        def run(batch):
            texts = [extract_text(x) for x in batch.column(2).to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [id_column, url, "text", "n_chars"])

        return run

    return arrow_map(pages.select(id_column, url, source), f"{id_column} {kinds[id_column]}, {url} {kinds[url]}, text string, n_chars long", make, 2)
