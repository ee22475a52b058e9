"""Main-text extraction from web pages by a linear-chain conditional random field over leaf blocks.

A page is read into its leaf blocks: runs of text between the tags that break a line. Each block has features of its ancestors
(tags, class, id and role words) and of its text (length, share of links, marks). The chain labels all blocks of a page together, by Viterbi;
the blocks labelled as main text, in page order, are the result. It is trained on pages made and labelled by ``labelled_pages``.
"""

from __future__ import annotations

import html
import random
import re
from collections.abc import Iterator
from functools import lru_cache
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairsample.llm.crf import Chain, padded

WIDTH = 1 << 16
# Elements of the HTML standard.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr br math mi mn mo mrow msup msub mfrac msqrt mtext semantics".split()
)
#: Elements whose content isn't shown; the first two go on to the end of the page where they aren't closed, the others count as ordinary elements then.
RAW = frozenset("script style".split())
HIDDEN = RAW | frozenset("noscript template svg iframe".split())
#: Start tags that end an open element of these names.
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
#: Elements that such an implied end doesn't reach beyond.
KEEPS = frozenset("ul ol dl table tbody thead select article section div body html".split())
TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*+(?:>|\Z)|<(/?)([A-Za-z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>|<(/?)([A-Za-z][^\s/>]*+)([^>]*+)>", re.S)
ATTRIBUTE = re.compile(r"(?:^|\s)(class|id|role|itemprop|aria-label|hidden)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
NAME = re.compile(r"[a-z]+")


class Leaf:
    """A block: its ancestors from the outside in, each a tag with its attribute words, its text, and the characters inside links."""

    __slots__ = ("path", "text", "linked")

    def __init__(self, path: tuple, text: str, linked: int) -> None:
        self.path, self.text, self.linked = path, text, linked


@lru_cache(maxsize=20_000)
def _words(attributes: str) -> tuple[str, ...]:
    found = []
    for m in ATTRIBUTE.finditer(attributes):
        value = next((v for v in m.groups()[1:] if v is not None), "")
        spaced = re.sub(r"([a-z])([A-Z])", r"\1 \2", value).lower()
        found += [f"{m[1].lower()}={w}" for w in NAME.findall(spaced)] or [m[1].lower()]
    return tuple(dict.fromkeys(found))


def leaves(page: str) -> list[Leaf]:
    """The leaf blocks of a page with text, in page order. Broken nesting is mended as browsers mend the common cases."""
    stack: list[tuple[str, tuple[str, ...]]] = []
    found: list[Leaf] = []
    parts: list[str] = []
    linked = anchors = 0
    at, end = 0, len(page)

    def flush() -> None:
        nonlocal parts, linked
        text = " ".join("".join(parts).split())
        if text:
            found.append(Leaf(tuple(x for x in stack if x[0] not in INLINE), text, linked))
        parts, linked = [], 0

    def say(raw: str) -> None:
        nonlocal linked
        if raw:
            text = html.unescape(raw) if "&" in raw else raw
            parts.append(text)
            if anchors:
                linked += len(text.strip())

    def close(k: int) -> None:
        """End all open elements from the k-th on."""
        nonlocal anchors
        anchors -= sum(x[0] == "a" for x in stack[k:])
        del stack[k:]

    while at < end:
        lt = page.find("<", at)
        if lt < 0:
            say(page[at:])
            break
        m = TAG.match(page, lt)
        if m is None:
            say(page[at : lt + 1])
            at = lt + 1
            continue
        say(page[at:lt])
        at = m.end()
        name = m[2] or m[5]
        if name is None:
            continue
        closing, name, attributes = bool(m[1] or m[4]), name.lower(), m[3] if m[2] else m[6]
        if closing:
            if name == "br":
                parts.append(" ")
                continue
            if name not in INLINE:
                flush()
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == name:
                    close(k)
                    break
                if name in INLINE and stack[k][0] not in INLINE:
                    break
            continue
        if name in HIDDEN:
            ended = attributes.endswith("/") and name not in RAW
            found_end = None if ended else re.compile(f"</{name}\\b[^>]*>", re.I).search(page, at)
            if ended or found_end or name in RAW:
                at = at if ended else found_end.end() if found_end else end
                continue
        if name == "br":
            parts.append(" ")
            continue
        if name not in INLINE:
            flush()
            for k in range(len(stack) - 1, -1, -1):
                open_ = stack[k][0]
                if open_ in ENDS.get(name, ()) or open_ == "p":
                    close(k)
                    if open_ != "p":
                        break
                elif open_ in KEEPS:
                    break
        if name not in VOID:
            stack.append((name, _words(attributes) if attributes else ()))
            anchors += name == "a"
    flush()
    return found


def _bucket(x: float, steps: tuple) -> int:
    return sum(x >= s for s in steps)


@lru_cache(maxsize=50_000)
def _path_features(path: tuple) -> tuple[int, ...]:
    names = ["bias"]
    for depth, (tag, words) in enumerate(reversed(path)):
        if depth < 3:
            names.append(f"up{depth} {tag}")
        names.append(f"in {tag}")
        names += [f"word {w.split('=')[-1]}" for w in words]
        names += [f"{tag} {w.split('=')[-1]}" for w in words]
    return tuple(crc32(n.encode()) % WIDTH for n in dict.fromkeys(names))


def features(page: list[Leaf]) -> list[list[int]]:
    out = []
    for k, leaf in enumerate(page):
        text, n = leaf.text, len(leaf.text)
        names = [
            f"length {_bucket(n, (10, 25, 60, 120, 300))}",
            f"links {_bucket(leaf.linked / n, (0.01, 0.3, 0.7, 0.95))}",
            f"stops {_bucket(text.count('.') + text.count(','), (1, 3, 8))}",
            f"ends {text[-1] if not text[-1].isalnum() else 'a'}",
            f"place {_bucket(k, (1, 4))} {_bucket(len(page) - k, (2, 4))}",
        ]
        if "©" in text:
            names.append("copyright")
        out.append([*_path_features(leaf.path), *(crc32(x.encode()) % WIDTH for x in names)])
    return out


def labelled_pages(count: int = 500, seed: int = 5) -> Iterator[tuple[list[Leaf], list[int]]]:
    """Made-up pages with the label of each leaf block, 1 for main text: many layouts, names, broken tags and texts of all kinds."""
    rng = random.Random(seed)
    pick = rng.choice
    syllables = [a + b for a in "bcdfglmnprstvz" for b in ("a", "e", "i", "o", "u", "er", "an", "ou")]
    mark = {}

    def word() -> str:
        return "".join(pick(syllables) for _ in range(rng.randint(1, 4)))

    def words(low: int, high: int) -> str:
        kind = rng.random()
        out = [word() for _ in range(rng.randint(low, high))]
        if kind < 0.1:
            out = [w + pick(["###", "%%%", "***", "$$$", "&amp;&amp;&amp;"]) for w in out]
        elif kind < 0.18:
            out = [w.upper() + "!!" for w in out]
        elif kind < 0.28:
            out = [w if rng.random() < 0.7 else str(rng.randint(0, 9999)) for w in out]
        else:
            out = [w + pick(["", "", "", "", ",", "."]) for w in out]
        return " ".join(out).capitalize() + pick([".", ".", ".", "", "!", "?"])

    def said(main: bool, low: int, high: int) -> str:
        # a serial number in the text tells the labels of leaves after parsing
        key = f"q{len(mark)}x"
        mark[key] = main
        return f"{key} {words(low, high)}"

    def attr(*names: str) -> str:
        extra = pick(["", "", " wrap", f" {word()}", " clearfix"])
        return f' {pick(["class", "class", "id"])}="{pick(names)}{extra}"'

    def links(n: int) -> str:
        # a menu's words stand in its links
        items = [f'<a href="/{word()}">{said(False, 1, 2)}</a>' for _ in range(n)]
        return "<ul>" + "".join(f"<li>{x}</li>" for x in items) + "</ul>" if rng.random() < 0.7 else " ".join(f"<div>{x}</div>" for x in items)

    def menu() -> str:
        tag, a = pick([("nav", ""), ("nav", attr("menu", "main-nav")), ("div", attr("nav", "navbar", "menu", "navigation", "breadcrumb", "breadcrumbs", "topmenu")), ("ul", attr("menu", "nav"))])
        return f"<{tag}{a}>{links(rng.randint(2, 7))}</{tag}>"

    def aside() -> str:
        tag, a = pick([("aside", ""), ("aside", attr("sidebar", "related")), ("div", attr("sidebar", "side-bar", "widget", "related", "related-posts", "recommended", "popular", "trending"))])
        return f"<{tag}{a}>" + pick([f"<h3>{said(False, 1, 4)}</h3>", ""]) + pick([links(3), f"<p>{said(False, 4, 30)}</p>"]) + f"</{tag}>"

    def advert() -> str:
        tag, a = pick([("div", attr("ad", "ads", "advert", "advertisement", "banner", "sponsored", "promo", "ad-slot")), ("section", attr("ad", "promo", "sponsor")), ("ins", attr("adsbygoogle"))])
        return f"<{tag}{a}>{said(False, 3, 25)}</{tag}>"

    def notice() -> str:
        a = attr("cookie", "cookie-banner", "cookie-notice", "gdpr", "consent", "notice", "popup", "modal", "newsletter", "subscribe", "alert", "paywall", "share", "social")
        return f"<{pick(['div', 'section', 'aside'])}{a}><p>{said(False, 4, 25)}</p>" + pick(["", f"<button>{said(False, 1, 2)}</button>"]) + "</div>"

    def form() -> str:
        fields = "".join(f"<label>{said(False, 1, 2)}</label><input name=q>" for _ in range(rng.randint(1, 3)))
        return f"<form{pick(['', attr('search', 'login', 'signup', 'contact')])}>{pick(['<p>' + said(False, 2, 12) + '</p>', ''])}{fields}<button>{said(False, 1, 2)}</button>{pick(['<select><option>' + said(False, 1, 1) + '<option>' + said(False, 1, 1) + '</select>', '<textarea>' + said(False, 1, 3) + '</textarea>', ''])}</form>"

    def comments() -> str:
        one = lambda: f"<{pick(['div', 'li', 'article'])}{attr('comment', 'reply', 'comment-body')}><p>{said(False, 2, 40)}</p></div>"
        return f"<{pick(['section', 'div', 'ol'])}{attr('comments', 'comment-list', 'commentlist', 'discussion', 'respond', 'disqus')}><h3>{said(False, 1, 3)}</h3>" + "".join(one() for _ in range(rng.randint(1, 4))) + "</div>"

    def body() -> str:
        out = [f"<h1>{said(True, 2, 10)}</h1>"] if rng.random() < 0.85 else []
        for _ in range(rng.randint(0, 10)):
            r = rng.random()
            if r < 0.55:
                out.append(f"<p>{said(True, 1, 60)}{pick(['</p>', '</p>', '</p>', '', '<br>'])}")
            elif r < 0.63:
                out.append(f"<p><b>{said(True, 1, 40)}{pick(['</b></p>', '<br>', ''])}")
            elif r < 0.7:
                out.append(f"<h{pick('234')}>{said(True, 1, 6)}</h2>")
            elif r < 0.77:
                out.append(f"<{pick(['ul', 'ol'])}>" + "".join(f"<li>{said(True, 1, 15)}{pick(['</li>', ''])}" for _ in range(rng.randint(1, 4))) + "</ul></ol>")
            elif r < 0.82:
                out.append(f"<blockquote>{pick(['', '<p>'])}{said(True, 2, 30)}</blockquote>")
            elif r < 0.86:
                out.append("<table>" + "".join(f"<tr><td>{said(True, 1, 3)}</td><td>{said(True, 1, 3)}</td></tr>" for _ in range(2)) + "</table>")
            elif r < 0.89:
                out.append(f"<pre>{said(True, 1, 20)}</pre>")
            elif r < 0.92:
                out.append(f"<div>{said(True, 1, 40)}</div>")
            elif r < 0.95:
                out.append(f'<p>{said(True, 1, 10)} <a href="#">{words(1, 4)}</a> {words(1, 10)}</p>')
            else:
                out.append(f"<figure><img src=x><figcaption>{said(True, 1, 12)}</figcaption></figure>")
            if rng.random() < 0.12:
                out.append(pick([advert, aside, notice, form])())
        if rng.random() < 0.12:
            out.append(comments())
        return "".join(out)

    for _ in range(count):
        mark.clear()
        tag, a = pick([("article", ""), ("article", ""), ("article", attr("post", "story", "entry")), ("main", ""), ("div", attr("content", "main-content", "post", "entry", "entry-content", "article", "article-body", "story", "post-body", "main", "text")), ("section", attr("content", "article", "post"))])
        article = f"<{tag}{a}>{body()}</{tag}>"
        if rng.random() < 0.3:
            article = f"<{pick(['div', 'main'])}{attr('container', 'wrapper', 'page', 'layout', 'row', 'content', 'main')}>{article}{aside() if rng.random() < 0.4 else ''}</div></main>"
        head = [f"<{pick(['header', 'div'])}{attr('header', 'site-header', 'masthead', 'topbar', 'page-header')}>{pick(['<h1>' + said(False, 1, 4) + '</h1>', '<a href=/>' + said(False, 1, 3) + '</a>', ''])}{menu() if rng.random() < 0.4 else '<p>' + said(False, 1, 12) + '</p>'}</div></header>"] if rng.random() < 0.5 else []
        before = [f() for f in (menu, notice, advert, aside, form) if rng.random() < 0.45]
        after = [f() for f in (comments, aside, notice, advert, form, menu) if rng.random() < 0.35]
        rng.shuffle(before)
        rng.shuffle(after)
        foot = pick([f"<footer>&copy; {said(False, 1, 20)}</footer>", f"<footer{attr('footer', 'site-footer')}>{links(3)}<p>&copy; {said(False, 2, 12)}</p></footer>", f"<div{attr('footer', 'site-footer', 'bottom', 'copyright')}>{said(False, 2, 20)}</div>", ""])
        title = f"<head><title>{said(False, 2, 10)}</title></head>" if rng.random() < 0.9 else ""
        page = leaves(f"<html>{title}<body>{''.join(head + before)}{article}{''.join(after)}{foot}{pick(['</body></html>', ''])}")
        labels = []
        for leaf in page:
            keys = [k for k in re.findall(r"\bq\d+x\b", leaf.text.lower()) if k in mark]
            labels.append(int(bool(keys) and all(mark[k] for k in keys)))
            leaf.text = re.sub(r"(?i)\bq\d+x ?", "", leaf.text) or "-"
        yield page, labels


def train(count: int = 700, seed: int = 5) -> Chain:
    rows: list[list[int]] = []
    sequences = []
    for page, labels in labelled_pages(count, seed):
        if page:
            sequences.append((np.arange(len(rows), len(rows) + len(page)), np.array(labels)))
            rows += features(page)
    return Chain(WIDTH, 2).fit(rows, sequences, rounds=8, size=32)


def main_text(chain: Chain, pages: list[list[Leaf]]) -> list[str]:
    """The main text of each page: its blocks labelled 1, joined by line feeds."""
    return ["\n".join(leaf.text for leaf, label in zip(page, labels, strict=True) if label) for page, labels in zip(pages, label_pages(chain, pages), strict=True)]


def label_pages(chain: Chain, pages: list[list[Leaf]]) -> list[list[int]]:
    lengths = np.array([len(p) for p in pages], np.int64)
    out: list[list[int]] = [[] for _ in pages]
    full = np.flatnonzero(lengths)
    order = full[np.argsort(-lengths[full], kind="stable")]
    at = 0
    while at < len(order):
        chosen = order[at : at + max(1, min(512, 200_000 // int(lengths[order[at]])))]
        at += len(chosen)
        emission, _ = padded(chain.emissions([f for i in chosen for f in features(pages[i])]), lengths[chosen])
        for i, labels in zip(chosen.tolist(), chain.viterbi_all(emission, lengths[chosen]), strict=True):
            out[i] = labels
    return out


def extract(pages: DataFrame, chain: Chain | None = None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """The main text of every page from its whole source, as (id_col, url_col, text, n_chars).

    Character references are decoded, white space inside a block is one space, blocks are trimmed and joined by one line feed; nothing is cut
    off. A null or empty page and one without main text give an empty text. Null ids and repeated rows are kept; other columns are not read.
    """
    sent = pages.sparkSession.sparkContext.broadcast(chain if chain is not None else train())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts: list[str] = []
            for at in range(0, batch.num_rows, 200):
                texts += main_text(sent.value, [leaves(x.as_py() or "") for x in batch.column(2).slice(at, 200)])
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], pa.array(texts, pa.string())], names=["key", "url", "text"])

    source = pages.select(F.col(id_col).cast("long").alias("key"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    found = source.mapInArrow(run, "key long, url string, text string")
    return found.select(F.col("key").alias(id_col), F.col("url").alias(url_col), "text", F.length("text").cast("long").alias("n_chars"))
