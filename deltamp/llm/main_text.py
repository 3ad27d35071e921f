"""Main text of web pages by a linear-chain conditional random field over leaf blocks.

A tolerant scanner turns a page into leaf blocks: runs of text that no block element interrupts, with the
tags, classes and ids of all ancestors. A block's features are its ancestors and the shape of its text
(words, share of link text, end mark, ...). The field has two labels, text and rest, with weights for
the features and for neighbouring labels; Viterbi decoding labels all blocks of a page at once.

The given tables hold no labelled pages, so the field is trained on pages that ``labelled_pages`` composes from
common layouts with known labels: menus, headers, footers, sidebars, notices, adverts, forms and reader comments
around (and partly inside) articles in several kinds of container, with invented words.

Defined cases: a null or empty page has an empty text; scripts, styles, markup comments and the head never
are blocks; the head ends at its end tag or at the first text or start tag that may not stand in it;
an unclosed tag, comment or quote takes the rest of the page, a quote that is never closed is none; a page without
blocks has an empty text; a page of any shape is read in time proportional to its length; repeated rows are treated alike; other columns are kept, those called like the results are replaced.
"""

from __future__ import annotations

import html
import random
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import read

#: Elements inside a line of text, elements without content, elements whose content is no text, and
#: for an opening tag the open elements that it ends, up to one of the last group.
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q ruby rp rt s samp small span strike strong sub sup time tt u var wbr br img".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
HIDDEN = frozenset("script style noscript template iframe object svg math canvas title textarea select datalist audio video".split())
ENDS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}

#: Elements that leave the head open; any other start tag, and text, ends it even without an end tag.
HEAD = frozenset("html head title meta link base basefont bgsound script style noscript template".split())

_NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_MARK = re.compile(r"[>\"']")
#: Character references of more digits than a code point has; the standard unescaping can't take very long ones.
_LONG = re.compile(r"&#(?:[0-9]{8,}|[xX][0-9a-fA-F]{7,});?")
_NAMED = re.compile(r"""(?:^|\s)(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.IGNORECASE)
_PARTS = re.compile(r"[a-z]+")
_NONE: frozenset[str] = frozenset()


@dataclass
class Block:
    text: str
    where: frozenset[str]
    link: float


def _unescaped(text: str) -> str:
    def short(m: re.Match) -> str:
        digits = m[0].strip("&#;xX").lstrip("0")
        return f"&#{'x' if m[0][2] in 'xX' else ''}{digits or 0};" if len(digits) < 8 else "\ufffd"

    return html.unescape(_LONG.sub(short, text) if "&#" in text else text)


class Scanner:
    """Splits pages into leaf blocks in one pass; sets of ancestor features are shared between pages.

    With ``vocabulary`` only the features in it are kept, so a set is never larger, however deep a page is nested.
    """

    def __init__(self, vocabulary: frozenset[str] | None = None) -> None:
        self.sets: dict[tuple[frozenset[str], str, str], frozenset[str]] = {}
        self.vocabulary = vocabulary

    def _inside(self, outer: frozenset[str], tag: str, rest: str) -> frozenset[str]:
        names = " ".join(x for m in _NAMED.findall(rest) for x in m) if "=" in rest else ""
        key = (outer, tag, names)
        if (known := self.sets.get(key)) is None:
            if len(self.sets) > 50_000:
                self.sets.clear()
            spaced = re.sub(r"(?<=[a-z])(?=[A-Z])", " ", names).lower()
            own = {f"t:{tag}"} | {f"c:{w}" for w in _PARTS.findall(spaced)}
            if self.vocabulary is not None:
                own &= self.vocabulary
            known = self.sets[key] = outer if own <= outer else outer | own
        return known

    def blocks(self, page: str) -> list[Block]:
        out: list[Block] = []
        stack: list[tuple[str, frozenset[str]]] = []
        places: dict[str, list[int]] = {}  # of each tag's open elements in the stack
        held: list[str] = []
        linked = total = 0
        at, n, quoted = 0, len(page), True

        def flush() -> None:
            nonlocal linked, total
            if held:
                text = " ".join("".join(held).split())
                if text and not places.get("head"):
                    out.append(Block(text, stack[-1][1] if stack else _NONE, linked / max(1, total)))
                held.clear()
                linked = total = 0

        def close(depth: int) -> None:
            """Closes all elements from this place of the stack on."""
            while len(stack) > depth:
                places[stack.pop()[0]].pop()

        def last(tags: set[str]) -> int:
            return max((p[-1] for t in tags if (p := places.get(t))), default=-1)

        def say(text: str) -> None:
            nonlocal linked, total
            if text:
                if (head := places.get("head")) and not text.isspace():
                    close(head[-1])
                held.append(_unescaped(text) if "&" in text else text)
                total += len(text)
                linked += len(text) if places.get("a") else 0

        while at < n:
            lt = page.find("<", at)
            if lt < 0:
                say(page[at:])
                break
            say(page[at:lt])
            if page.startswith("<!--", lt):
                end = page.find("-->", lt + 4)
                at = n if end < 0 else end + 3
                continue
            if page.startswith(("<!", "<?"), lt):
                end = page.find(">", lt)
                at = n if end < 0 else end + 1
                continue
            m = _NAME.match(page, lt)
            if m is None:
                say("<")
                at = lt + 1
                continue
            stop = _tag_end(page, m.end()) if quoted else -1
            if stop < 0:  # an open quote or no end: from here on a tag ends at its first >
                quoted, stop = False, page.find(">", m.end())
            if stop < 0:  # a tag without an end takes the rest of the page
                break
            rest, at, tag, end = page[m.end() : stop], stop + 1, m[2].lower(), m[1] == "/"
            if (head := places.get("head")) and not end and tag not in HEAD:
                close(head[-1])
            if tag in HIDDEN:
                if not end and not rest.endswith("/"):
                    done = re.compile(rf"</{tag}\s*>", re.IGNORECASE).search(page, at)
                    at = done.end() if done else n
                continue
            if tag == "br":
                say(" ")
                continue
            if tag not in INLINE:
                flush()
            if end:
                if places.get(tag):
                    close(places[tag][-1])
                continue
            if tag in VOID:
                continue
            if tag not in INLINE and places.get("p"):
                close(places["p"][-1])
            if tag in ENDS:
                ended, limit = ENDS[tag]
                if (k := last(ended)) > last(limit):
                    close(k)
            outer = stack[-1][1] if stack else _NONE
            places.setdefault(tag, []).append(len(stack))
            stack.append((tag, outer if tag in INLINE else self._inside(outer, tag, rest)))
        flush()
        return out


def _tag_end(page: str, at: int) -> int:
    """Place of the first > outside of quotes, -1 if there is none."""
    while m := _MARK.search(page, at):
        if m[0] == ">":
            return m.start()
        at = page.find(m[0], m.end()) + 1
        if not at:
            break
    return -1


def shape(b: Block) -> tuple[str, ...]:
    """Features of a block's text."""
    t = b.text
    words = t.count(" ") + 1
    return (
        f"words:{words.bit_length()}", f"link:{min(4, int(b.link * 4.99))}", f"last:{'stop' if t[-1] in '.!?…:»”' else 'letter' if t[-1].isalpha() else 'other'}",
        f"first:{'upper' if t[0].isupper() else 'other'}", f"mark:{'©' in t and words < 40}",
    )


@dataclass
class Model:
    weights: dict[str, float] = field(default_factory=dict)  # for label 1 against label 0
    step: np.ndarray = field(default_factory=lambda: np.zeros((2, 2)))
    start: np.ndarray = field(default_factory=lambda: np.zeros(2))

    def emission(self, b: Block) -> float:
        return sum(self.weights.get(f, 0.0) for f in (*b.where, *shape(b), "always"))


def viterbi(e: list[float], m: Model) -> list[int]:
    """Best labels for the blocks' scores."""
    if not e:
        return []
    (t00, t01), (t10, t11) = m.step.tolist()
    s0, s1 = float(m.start[0]), float(m.start[1]) + e[0]
    back = []
    for x in e[1:]:
        from0, from1 = (0 if s0 + t00 >= s1 + t10 else 1), (0 if s0 + t01 > s1 + t11 else 1)
        back.append((from0, from1))
        s0, s1 = max(s0 + t00, s1 + t10), max(s0 + t01, s1 + t11) + x
    label = int(s1 > s0)
    out = [label]
    for b in reversed(back):
        label = b[label]
        out.append(label)
    return out[::-1]


def train(pages: list[tuple[list[Block], list[int]]], epochs: int = 8, rate: float = 0.3, decay: float = 1e-4) -> Model:
    """Likelihood ascent page by page with AdaGrad steps; the gradient comes from forward and backward sums."""
    m, past = Model(), {}
    tpast, spast = np.full((2, 2), 1e-2), np.full(2, 1e-2)
    order = random.Random(3)
    pages = [(b, y, [(*sorted(x.where), *shape(x), "always") for x in b]) for b, y in pages if b]
    for _ in range(epochs):
        order.shuffle(pages)
        for _, y, feats in pages:
            n = len(y)
            e = np.zeros((n, 2))
            e[:, 1] = [sum(m.weights.get(f, 0.0) for f in fs) for fs in feats]
            a, b = np.zeros((n, 2)), np.zeros((n, 2))
            a[0] = m.start + e[0]
            for i in range(1, n):
                a[i] = np.logaddexp(a[i - 1, 0] + m.step[0], a[i - 1, 1] + m.step[1]) + e[i]
            for i in range(n - 2, -1, -1):
                v = b[i + 1] + e[i + 1]
                b[i] = np.logaddexp(m.step[:, 0] + v[0], m.step[:, 1] + v[1])
            z = np.logaddexp(*a[-1])
            p = np.exp(a + b - z)
            gt = np.zeros((2, 2))
            for i in range(1, n):
                gt -= np.exp(a[i - 1][:, None] + m.step + (e[i] + b[i])[None, :] - z)
                gt[y[i - 1], y[i]] += 1
            gs = -p[0]
            gs[y[0]] += 1
            tpast += gt**2
            spast += gs**2
            m.step += rate * gt / np.sqrt(tpast)
            m.start += rate * gs / np.sqrt(spast)
            for i, fs in enumerate(feats):
                g = (y[i] == 1) - float(p[i, 1])
                if abs(g) > 1e-4:
                    for f in fs:
                        w = m.weights.get(f, 0.0)
                        d = g - decay * w
                        past[f] = past.get(f, 1e-2) + d * d
                        m.weights[f] = w + rate * d / past[f] ** 0.5
    return m


def _page(r: random.Random) -> str:
    """One page; text that belongs to the article holds a private-use mark."""
    syllables = "ba ce di fo gu ha je ki lo mu na pe qui ro su ta ve xi yo zé ün ça øs ñe".split()
    word = lambda: "".join(r.choice(syllables) for _ in range(r.randint(1, 4)))
    words = lambda a, b: " ".join(word() for _ in range(r.randint(a, b)))

    def sentence(a: int = 1, b: int = 25) -> str:
        """Mostly plain; now and then shouted, with bars or with strings of marks, in articles as elsewhere."""
        t, kind = words(a, r.choice((2, b))), r.random()
        if kind < 0.05:
            return t.upper().replace(" ", "!! ") + "!!"
        if kind < 0.1:
            return t.replace(" ", " | ")
        if kind < 0.15:
            return t.replace(" ", r.choice(("$$$ ", "&amp;&amp; ", "### "))) + r.choice(("", "***"))
        return t.capitalize() + r.choice("....!?")

    prose = lambda a=1, b=6: " ".join(sentence() for _ in range(r.randint(a, b)))
    main = lambda t: "" + t
    link = lambda t: f'<a href="/{word()}">{t}</a>'

    def links(n: int) -> str:
        return "<ul>" + "".join(f"<li>{link(words(1, 3))}</li>" for _ in range(n)) + "</ul>" if r.random() < 0.7 else " | ".join(link(word()) for _ in range(n))

    def some(*names: str) -> str:
        """Classes or ids with one of the names, now and then with a prefix or ending."""
        name = r.choice(names)
        return f'{r.choice(("class", "class", "id"))}="{r.choice(("", "", word() + "-"))}{name}{r.choice(("", "", "-" + word(), " " + word()))}"'

    def aside() -> str:
        kind = r.randint(0, 11)
        talk = prose(1, 3)
        return (
            f"<nav>{links(r.randint(2, 8))}</nav>", f'<div {some("menu", "nav", "navbar", "navigation", "breadcrumb", "breadcrumbs", "pagination", "toc")}>{links(r.randint(2, 8))}</div>',
            f'<aside{r.choice(("", " " + some("related", "sidebar")))}><h3>{words(1, 4)}</h3><p>{talk}</p>{links(3)}</aside>', f'<div {some("sidebar", "widget", "related", "recommended", "popular", "newsletter", "trending")}><h2>{words(1, 4)}</h2><p>{talk}</p></div>',
            f'<div {some("ad", "ads", "advert", "advertisement", "sponsored", "promo", "banner", "sponsor")}>{r.choice((talk, f"<p>{talk}</p>"))}</div>', f'<div {some("cookie", "cookies", "consent", "notice", "gdpr", "popup", "modal", "alert")}><p>{talk}</p><button>{word()}</button></div>',
            f'<form {some("search", "login", "subscribe", "signup")}><label>{words(1, 3)}</label><input type="text"><p>{talk}</p><button>{words(1, 2)}</button></form>', f'<div {some("share", "social", "tags", "meta", "byline", "author-box")}>{links(3)}</div>',
            f'<section {some("comments", "comment-list", "replies", "discussion", "responses")}><h3>{words(1, 3)}</h3>' + "".join(f'<div {some("comment", "reply")}><p>{prose(1, 3)}</p></div>' for _ in range(r.randint(1, 4))) + "</section>",
            f'<ol {some("comments", "commentlist")}>' + "".join(f"<li><p>{prose(1, 3)}</p></li>" for _ in range(r.randint(1, 3))) + "</ol>", f'<div {some("disclaimer", "copyright", "legal")}>&copy; {word()} {words(2, 8)}</div>', f"<dialog><p>{talk}</p></dialog>",
        )[kind]

    def part() -> str:
        kind = r.randint(0, 13)
        t = main(prose())
        if kind < 7:
            return f"<p>{t}" + r.choice(("</p>", "</p>", ""))
        return (
            f"<p><b>{t}<br>", f"<h2>{main(words(1, 6))}</h2><p>{t}</p>", f"<ul><li>{t}</li><li>{main(words(1, 9))}</li></ul>", f"<blockquote><p>{t}</p></blockquote>",
            f"<div>{t}</div>", f"<figure><img src=x><figcaption>{main(sentence())}</figcaption></figure>", f"<pre>{main(words(2, 9))}</pre><table><tr><td>{main(words(1, 3))}</td><td>{main(words(1, 3))}</td></tr></table>",
        )[kind - 7]

    body = "".join(part() + (aside() if r.random() < 0.08 else "") for _ in range(r.randint(1, 12)))
    title = main(words(1, 9))
    open_, close = r.choice((("<article>", "</article>"), ("<article>", "</article>"), ("<article>", "</article>"), ("", ""), (f"<article {some('post', 'entry', 'story')}>", "</article>"), ("<main>", "</main>"), ("<main><article>", "</article></main>"), (f"<div {some('content', 'article', 'post', 'entry', 'story', 'main', 'body')}>", "</div>"), (f"<section {some('content', 'article', 'story')}>", "</section>")))
    article = f"{open_}<h1>{title}</h1>{body}{close}"
    top = r.choice(("", f"<header>{r.choice(('', f'<h1>{words(1, 3)}</h1>'))}<p>{sentence()}</p>{links(3)}</header>", f'<div {some("header", "masthead", "top")}><p>{sentence()}</p></div>'))
    bottom = r.choice(("", f"<footer><p>&copy; {word()} &middot; {sentence()}</p></footer>", f"<footer>&copy; {word()} &middot; {sentence()}</footer>", f'<div {some("footer", "bottom")}>{links(4)}<p>{prose(1, 2)}</p></div>'))
    before, after = ("".join(aside() for _ in range(r.randint(0, 3))) for _ in range(2))
    return f"<html><head><title>{words(1, 5)}</title><style>p{{}}</style></head><body>{top}{before}{article}{after}{bottom}</body></html>"


def labelled_pages(n: int, seed: int = 1) -> list[tuple[list[Block], list[int]]]:
    r, scanner, out = random.Random(seed), Scanner(), []
    for _ in range(n):
        blocks = scanner.blocks(_page(r))
        labels = [int("" in b.text) for b in blocks]
        out.append(([Block(b.text.replace("", ""), b.where, b.link) for b in blocks], labels))
    return out


@lru_cache(maxsize=2)
def trained(pages: int = 700) -> Model:
    return train(labelled_pages(pages))


class Extractor:
    """Scores blocks with what the model knows of each set of ancestors kept at hand."""

    def __init__(self, model: Model) -> None:
        self.model, self.scanner = model, Scanner(frozenset(model.weights))
        self.known: dict[frozenset[str], float] = {}
        self.shapes: dict[tuple[str, ...], float] = {}

    def text(self, page: str) -> str:
        blocks, scores = self.scanner.blocks(page), []
        get = self.model.weights.get
        for b in blocks:
            if (s := self.known.get(b.where)) is None:
                if len(self.known) > 50_000:
                    self.known.clear()
                s = self.known[b.where] = sum(get(f, 0.0) for f in b.where) + get("always", 0.0)
            form = shape(b)
            if (x := self.shapes.get(form)) is None:
                x = self.shapes[form] = sum(get(f, 0.0) for f in form)
            scores.append(s + x)
        return " ".join(b.text for b, y in zip(blocks, viterbi(scores, self.model), strict=True) if y)


def extract(pages: DataFrame, model: Model | None = None, page: str = "html", out: str = "text") -> DataFrame:
    """``pages`` with the main text."""
    shared = pages.sparkSession.sparkContext.broadcast(model or trained())

    @F.arrow_udf("string")
    def extracted(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        extractor = Extractor(shared.value)
        for part in parts:
            yield pa.array([extractor.text(x.as_py() or "") for x in part], pa.string())

    kept = [F.col(f"`{c}`") for c in pages.columns if c != out]
    return pages.select(*kept, extracted(F.col(f"`{page}`")).alias(out))


def op6_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = extract(read(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return out.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
