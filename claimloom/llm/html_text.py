"""Main-text extraction from web pages (operator 7): a linear-chain CRF over the DOM's leaf blocks.

A page is cut into leaf blocks (runs of text between block-level tags, in page order). Each has features of its
ancestors (tags, class, id and role words) and of its text (length, links, punctuation, place). A conditional random
field with two labels, fitted by stochastic gradient on pages that `training_pages` writes with known labels, is decoded
by Viterbi; blocks labelled as article are joined by one space.

Scripts, styles, templates, form controls, drawings, embedded media, comments in the markup and the head are no blocks; formulas
are text. A page may leave out head and body tags: the head ends with the first tag or text that cannot stand in it. An
unclosed tag ends with its parent, an unclosed control or drawing with the next block-level tag. Character references are
decoded, white space inside a block becomes one space. Null, empty and tag-less pages give their own text as far as the
field takes it, empty if none; repeated rows are extracted each; nothing is cut. Cutting takes time linear in the page.
"""

from __future__ import annotations

import html as entities
import math
import random
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import small_batches, table

_RAW = "script|style|textarea|title|iframe|noframes|noembed"  # their content holds no tags
_TOKEN = re.compile(
    rf"<!--.*?(?:-->|\Z)|<({_RAW})\b[^>]*+(?<!/)>.*?(?:</\1\s*+>|\Z)|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']|\"[^\"]*+\"|'[^']*+')*+)>|<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)>|<[!?][^>]*+>",
    re.S | re.I,
)
_ATTR = re.compile(r"\b(class|id|role|aria-label|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"']+))", re.I)
_NAME = re.compile(r"[a-z]+")
_MATH = "math mi mo mn ms mtext mrow mfrac msqrt mroot mstyle msup msub msubsup munder mover munderover mmultiscripts semantics"
_INLINE = frozenset(f"a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img {_MATH}".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_CLOSES_P = frozenset("address article aside blockquote div dl fieldset figure figcaption footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul details summary".split())
_PARTS = frozenset("li dt dd tr td th thead tbody tfoot caption body".split())
_SAME = {"li": ("li", ("ul", "ol", "menu")), "dt": ("dt dd", ("dl",)), "dd": ("dt dd", ("dl",)), "tr": ("tr td th", ("table",)), "td": ("td th", ("tr", "table")), "th": ("td th", ("tr", "table"))}
_SCOPE = frozenset("article aside body div footer form header html main nav section table td th li blockquote".split())
_HEAD = frozenset("html head base link meta title style script noscript template".split())
_HIDDEN = frozenset("template svg object canvas select button audio video datalist annotation annotation-xml".split())
_BREAKS = frozenset("svg canvas select button datalist annotation annotation-xml".split())  # a block-level tag ends them
_QUIET = frozenset(("svg", "annotation", "annotation-xml"))  # no block ends where they stand
_LETTER = re.compile(r"[^\W\d_]")


class Block:
    __slots__ = ("text", "tags", "last", "names", "linked")

    def __init__(self, text: str, tags: frozenset, last: str, names: frozenset, linked: int):
        self.text, self.tags, self.last, self.names, self.linked = text, tags, last, names, linked


class _Open:
    """The open elements, with counts of what a block's features ask for."""

    def __init__(self):
        self.stack: list[tuple[str, tuple]] = []
        self.tags: dict[str, int] = {}
        self.names: dict[str, int] = {}
        self.path: list[str] = []

    def push(self, tag: str, names: tuple) -> None:
        self.stack.append((tag, names))
        self.tags[tag] = self.tags.get(tag, 0) + 1
        if tag not in _INLINE:
            self.path.append(tag)
        for n in names:
            self.names[n] = self.names.get(n, 0) + 1

    def pop(self) -> None:
        tag, names = self.stack.pop()
        self.tags[tag] -= 1
        if not self.tags[tag]:
            del self.tags[tag]
        if tag not in _INLINE:
            self.path.pop()
        for n in names:
            self.names[n] -= 1
            if not self.names[n]:
                del self.names[n]

    def close(self, names, stop) -> None:
        """Close the innermost open element of these names, and all inside it, unless one of stop is met first."""
        if all(n not in self.tags for n in names):
            return
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] in names:
                while len(self.stack) > i:
                    self.pop()
                return
            if self.stack[i][0] in stop:
                return

    def hidden(self) -> str | None:
        """The innermost open element if its content is not shown: nothing else is opened inside one."""
        return self.stack[-1][0] if self.stack and self.stack[-1][0] in _HIDDEN else None


def blocks(page: str) -> list[Block]:
    out: list[Block] = []
    open_ = _Open()
    parts: list[str] = []
    linked, in_head = 0, False

    def flush() -> None:
        nonlocal linked
        text = " ".join(entities.unescape("".join(parts)).split())
        if text:
            tags = frozenset(t for t in open_.tags if t not in _INLINE)
            out.append(Block(text, tags, open_.path[-1] if open_.path else "none", frozenset(open_.names), min(linked, len(text))))
        parts.clear()
        linked = 0

    def take(piece: str) -> None:
        nonlocal linked, in_head
        if not piece or open_.hidden():
            return
        if in_head:
            if not piece.strip():
                return
            in_head = False
        parts.append(piece)
        if "a" in open_.tags:
            linked += len(piece.strip())

    at = 0
    for m in _TOKEN.finditer(page):
        if m.start() > at:
            take(page[at : m.start()])
        at = m.end()
        tag = m[3] or m[6]
        if tag is None:
            if m[1] and not open_.hidden():
                flush()
            continue
        tag, closing, attributes = tag.lower(), m[2] or m[5], m[4] or m[7] or ""
        if open_.hidden():
            if closing:
                if tag in _INLINE or tag not in open_.tags:
                    continue
            elif tag in _CLOSES_P or tag in _PARTS:
                while open_.hidden() in _BREAKS:
                    open_.pop()
                if open_.hidden():
                    continue
            else:
                if tag in _HIDDEN and not attributes.endswith("/"):
                    open_.push(tag, ())
                continue
        if tag == "br":
            parts.append(" ")
            continue
        inline = tag in _INLINE
        if not inline and tag not in _QUIET:
            flush()
        if tag == "head":
            in_head = not closing
            continue
        if in_head and tag not in _HEAD:
            in_head = False
        if closing:
            if tag in open_.tags:
                open_.close((tag,), _SCOPE | _CLOSES_P if inline else ())
            continue
        if tag in _CLOSES_P:
            open_.close(("p",), _SCOPE)
        if tag in _SAME:
            open_.close(_SAME[tag][0].split(), _SAME[tag][1])
        if tag in _VOID or attributes.endswith("/") and (inline or tag in _HIDDEN):
            continue
        names = ()
        if "=" in attributes:
            names = tuple(n for a in _ATTR.finditer(attributes) for n in _NAME.findall((a[2] or a[3] or a[4] or "").lower()) if n in _ASIDE or n in _BODY)
        open_.push(tag, names)
    take(page[at:])
    flush()
    return out


# Class, id and role words that page templates use for each kind of block.
KINDS = {
    "nav": "nav navbar navigation menu breadcrumb breadcrumbs topbar toc pagination pager skip tabs sitemap",
    "header": "header masthead banner branding logo topnav site tagline top",
    "footer": "footer copyright legal contentinfo bottom colophon foot imprint terms privacy",
    "aside": "sidebar aside widget related recommended complementary popular trending side rail more tags archive categories",
    "notice": "cookie cookies consent notice gdpr alert popup modal overlay paywall message warning info dialog",
    "ad": "ad ads advert advertisement advertising sponsored sponsor promo promotion banner adsense dfp commercial partner adbox",
    "form": "form search login signup subscribe newsletter register contact signin field",
    "comments": "comments comment reply replies discussion disqus respond thread commentlist reader feedback response reviews",
    "share": "share social follow sharing buttons toolbar actions tools print",
}
BODY = "content article post entry story body main text page articlebody prose single copy read"
_ASIDE = frozenset(" ".join(KINDS.values()).split()) - frozenset(BODY.split())
_BODY = frozenset(BODY.split())
_ASIDE_TAGS = frozenset(("nav", "footer", "aside", "form", "dialog"))


def features(b: Block) -> list[str]:
    words = b.text.split()
    k = len(words)
    last = b.text.rstrip("\"')”»]")[-1:]
    stops = sum(b.text.count(c) for c in ".!?。;:")
    density = b.linked / max(1, len(b.text))
    out = [f"t:{x}" for x in b.tags]
    out += [f"n:{x}" for x in b.names]
    inside = "art" if "article" in b.tags or "main" in b.tags else "out"
    tag = b.last
    out += [f"p:{tag}", f"in:{inside}", f"p:{tag}:{inside}", f"len:{min(8, int(math.log2(k + 1)))}", f"link:{int(density * 4)}", f"end:{last in '.!?。…'}", f"stops:{min(4, stops)}"]
    out += [f"long:{k >= 12 and density < 0.3}", f"long:{k >= 12 and density < 0.3}:{inside}", f"copy:{'©' in b.text}"]
    side = not _ASIDE.isdisjoint(b.names) or not _ASIDE_TAGS.isdisjoint(b.tags)
    out += [f"side:{side}:{inside}", f"side:{side}:{inside}:{tag}", f"body:{not _BODY.isdisjoint(b.names)}:{side}"]
    if not _LETTER.search(b.text):
        out.append("noletter")
    return out


class Field:
    """Two-label linear-chain CRF; label 1 is article text. Unknown features weigh nothing."""

    def __init__(self):
        self.weight: dict[str, float] = {}
        self.move = [[0.0, 0.0], [0.0, 0.0]]

    def scores(self, feats: list[list[str]]) -> list[float]:
        get = self.weight.get
        return [sum(get(f, 0.0) for f in fs) for fs in feats]

    def decode(self, score: list[float]) -> list[int]:
        """Viterbi."""
        (aa, ab), (ba, bb) = self.move
        x, y = 0.0, 0.0
        back = []
        for i, s in enumerate(score):
            if i:
                from0, from1 = x + ab, y + bb
                keep0, keep1 = x + aa, y + ba
                back.append((0 if keep0 >= keep1 else 1, 0 if from0 > from1 else 1))
                x, y = max(keep0, keep1), max(from0, from1) + s
            else:
                y = s
        if not score:
            return []
        out = [int(y > x)]
        for pair in reversed(back):
            out.append(pair[out[-1]])
        return out[::-1]

    def expected(self, score: list[float]) -> tuple[list[float], list[list[float]]]:
        """Marginals of label 1 and expected transitions (forward-backward, normalised at each step)."""
        n = len(score)
        e = [[math.exp(v) for v in r] for r in self.move]
        forward, backward = [], [[1.0, 1.0]] * n
        for i, s in enumerate(score):
            g = math.exp(max(-30.0, min(30.0, s)))
            p = forward[-1] if i else None
            a = [1.0, g] if p is None else [p[0] * e[0][0] + p[1] * e[1][0], (p[0] * e[0][1] + p[1] * e[1][1]) * g]
            z = a[0] + a[1]
            forward.append([a[0] / z, a[1] / z])
        for i in range(n - 2, -1, -1):
            g, q = math.exp(max(-30.0, min(30.0, score[i + 1]))), backward[i + 1]
            b = [e[k][0] * q[0] + e[k][1] * g * q[1] for k in (0, 1)]
            z = b[0] + b[1]
            backward[i] = [b[0] / z, b[1] / z]
        marginal, moves = [], [[0.0, 0.0], [0.0, 0.0]]
        for f, b in zip(forward, backward):
            z = f[0] * b[0] + f[1] * b[1]
            marginal.append(f[1] * b[1] / z)
        for i in range(1, n):
            g, f, b = math.exp(max(-30.0, min(30.0, score[i]))), forward[i - 1], backward[i]
            cell = [[f[j] * e[j][k] * (g if k else 1.0) * b[k] for k in (0, 1)] for j in (0, 1)]
            z = sum(map(sum, cell))
            for j in (0, 1):
                for k in (0, 1):
                    moves[j][k] += cell[j][k] / z
        return marginal, moves

    def fit(self, pages: list[tuple[list[list[str]], list[int]]], rounds: int = 12, rate: float = 0.25, decay: float = 1e-3, seed: int = 42) -> None:
        """Adagrad on the log-likelihood."""
        r, seen = random.Random(seed), {}
        order = list(range(len(pages)))
        for _ in range(rounds):
            r.shuffle(order)
            for at in order:
                feats, labels = pages[at]
                marginal, moves = self.expected(self.scores(feats))
                step: dict[str, float] = {}
                for fs, y, p in zip(feats, labels, marginal):
                    for f in fs:
                        step[f] = step.get(f, 0.0) + y - p
                for f, g in step.items():
                    w = self.weight.get(f, 0.0)
                    g -= decay * w
                    seen[f] = seen.get(f, 1e-2) + g * g
                    self.weight[f] = w + rate * g / math.sqrt(seen[f])
                for a, b in zip(labels, labels[1:]):
                    moves[a][b] -= 1.0
                for j in (0, 1):
                    for k in (0, 1):
                        self.move[j][k] -= 0.01 * moves[j][k]


def _words(r: random.Random, n: int) -> str:
    bits = r.choice(("th an er on re he in ed nd ha at en es of or nt ea ti to it st is", "de la en os el ci ón es ra do ll ar as que ñ", "ch er ein en sch ie be ge ung zu ü ß", "eau ou è ment tion ai re é le oi ç", "ка но ри та во ли", "語 文 字 本 日 人"))
    bits = bits.split()
    out = ["".join(r.choice(bits) for _ in range(r.randrange(1, 5))) for _ in range(n)]
    return " ".join(w + ("," if r.random() < 0.06 else "") for w in out)


def _sentences(r: random.Random, n: int) -> str:
    return " ".join(_words(r, r.choice((1, 2, 4, 8, 12, 20))).capitalize() + r.choice(".....?!") for _ in range(n))


def training_page(r: random.Random) -> str:
    """A page whose article blocks begin with the mark U+E001 and whose other blocks begin with U+E000."""
    no, yes = "\ue000", "\ue001"
    attr = lambda words: (lambda w: r.choice((f' class="{w}"', f' id="{w}"', f' class="{w} x{r.randrange(9)}"', f' class="{r.choice(("site", "page", "block", "l", "c"))}-{w}"')))(r.choice(words.split()))
    link = lambda: f'<li><a href="/{r.randrange(99)}">{no}{_words(r, r.randrange(1, 4))}</a></li>'

    def boiler(kind: str) -> str:
        named = attr(KINDS[kind])
        many = r.randrange(1, 8)
        if kind == "nav":
            rows = "".join(link() for _ in range(many))
            return r.choice((f"<nav><ul>{rows}</ul></nav>", f"<nav{named}><ul>{rows}</ul></nav>", f"<div{named}><ul>{rows}</ul></div>", f"<ul{named}>{rows}</ul>"))
        if kind == "header":
            return f"<header{r.choice(('', named))}><div>{no}{_words(r, 3)}</div><p>{no}{_words(r, r.randrange(2, 9))}</p></header>" if r.random() < 0.6 else f"<div{named}><h2>{no}{_words(r, 3)}</h2></div>"
        if kind == "footer":
            body = r.choice((f"{no}&copy; {_words(r, 2)} &middot; {_sentences(r, r.randrange(1, 4))}", f"<p>{no}{_sentences(r, 2)}</p><p>{no}© 2020 {_words(r, 2)}</p>", f"{no}{_sentences(r, 3)}"))
            return r.choice((f"<footer>{body}</footer>", f"<footer{named}>{body}</footer>", f"<div{named}>{body}</div>"))
        if kind == "aside":
            body = r.choice((f"<h3>{no}{_words(r, 2)}</h3><ul>{''.join(link() for _ in range(many))}</ul>", f"<p>{no}{_sentences(r, r.randrange(1, 5))}</p>", f"<h4>{no}{_words(r, 2)}</h4><p>{no}{_sentences(r, 3)}</p>"))
            return r.choice((f"<aside>{body}</aside>", f"<aside{named}>{body}</aside>", f"<div{named}>{body}</div>", f"<section{named}>{body}</section>"))
        if kind == "ad":
            return r.choice((f"<div{named}>{no}{_sentences(r, r.randrange(1, 4))}</div>", f"<div{named}><p>{no}{_sentences(r, 2)}</p><a href='#'>{no}{_words(r, 2)}</a></div>", f"<section{named}>{no}{_sentences(r, 2)}</section>", f"<aside{named}><p>{no}{_sentences(r, 2)}</p></aside>"))
        if kind == "notice":
            return r.choice((f"<div{named}><p>{no}{_sentences(r, r.randrange(1, 4))}</p></div>", f"<div{named} role='dialog'>{no}{_sentences(r, 2)}</div>", f"<section{named}><p>{no}{_sentences(r, 2)}</p></section>", f"<p{named}>{no}{_sentences(r, 2)}</p>"))
        if kind == "form":
            return f"<form{r.choice(('', named))}><label>{no}{_words(r, 2)}</label><input name=q><p>{no}{_sentences(r, r.randrange(1, 3))}</p></form>"
        if kind == "comments":
            one = lambda: r.choice((f"<div{named}><b>{no}{_words(r, 2)}</b><p>{no}{_sentences(r, r.randrange(1, 6))}</p></div>", f"<li{named}><p>{no}{_sentences(r, r.randrange(1, 6))}</p></li>", f"<article{attr(KINDS['comments'])}><p>{no}{_sentences(r, 3)}</p></article>"))
            body = "".join(one() for _ in range(many))
            outer = attr("comments discussion respond replies thread commentlist")
            return r.choice((f"<section{outer}><h3>{no}{_words(r, 2)}</h3>{body}</section>", f"<div{outer}>{body}</div>", f"<ol{outer}>{body}</ol>"))
        return f"<div{named}>" + "".join(f"<a href='#'>{no}{_words(r, 1)}</a> " for _ in range(many)) + "</div>"

    def para() -> str:
        text = _sentences(r, r.choice((1, 1, 2, 4, 8)))
        kind = r.random()
        if kind < 0.55:
            return f"<p>{yes}{text}</p>"
        if kind < 0.65:
            return f"<p><b>{yes}{text}<br>"
        if kind < 0.72:
            return f"<h{r.randrange(2, 5)}>{yes}{_words(r, r.randrange(1, 8))}</h3>"
        if kind < 0.79:
            return "<ul>" + "".join(f"<li>{yes}{_words(r, r.randrange(1, 15))}</li>" for _ in range(r.randrange(1, 5))) + "</ul>"
        if kind < 0.84:
            return f"<blockquote><p>{yes}{text}</p></blockquote>"
        if kind < 0.88:
            return f"<figure><img src=x><figcaption>{yes}{_words(r, 6)}.</figcaption></figure>"
        if kind < 0.92:
            return f"<table><tr><td>{yes}{_words(r, 2)}</td><td>{yes}{r.randrange(999)}</td></tr></table>"
        if kind < 0.95:
            return f"<pre>{yes}{_words(r, 9)}</pre>"
        return f"<p>{yes}{_words(r, 3)} <a href='/x'>{_words(r, 3)}</a> {text}</p>"

    title = f"<h1>{yes}{_words(r, r.randrange(1, 12))}</h1>"
    head = r.choice((title, title, f"<header>{title}<p>{yes}{_words(r, 4)}.</p></header>", ""))
    inner = [para() for _ in range(r.choice((0, 1, 1, 2, 3, 6, 12)))]
    for kind in ("ad", "share", "form", "aside", "notice"):
        if r.random() < 0.12:
            inner.insert(r.randrange(len(inner) + 1), boiler(kind))
    body = head + "".join(inner) + (boiler("comments") if r.random() < 0.15 else "")
    wrap = r.random()
    named = attr(BODY)
    if wrap < 0.5:
        body = f"<article>{body}</article>"
    elif wrap < 0.65:
        body = f"<article{named}>{body}</article>"
    elif wrap < 0.75:
        body = f"<main>{body}</main>"
    elif wrap < 0.95:
        body = f"<div{named}>{body}</div>"
    else:
        body = f"<div>{body}</div>"
    before = [boiler(k) for k in ("notice", "header", "nav", "ad", "form", "aside") if r.random() < 0.45]
    after = [boiler(k) for k in ("ad", "share", "aside", "comments", "form", "nav", "notice", "footer") if r.random() < 0.4]
    if r.random() < 0.7:
        after.append(boiler("footer"))
    return f"<html><head><title>x</title></head><body>{''.join(before)}{body}{''.join(after)}</body></html>"


def training_pages(n: int = 900, seed: int = 42) -> list[tuple[list[list[str]], list[int]]]:
    """Features and labels of the blocks of n written pages."""
    r, out = random.Random(seed), []
    for _ in range(n):
        found = blocks(training_page(r))
        labels = [int("\ue001" in b.text) for b in found]
        for b in found:
            b.text = " ".join(b.text.replace("\ue000", "").replace("\ue001", "").split()) or "-"
        out.append(([features(b) for b in found], labels))
    return out


@lru_cache(maxsize=1)
def trained(n: int = 900, seed: int = 42) -> Field:
    field = Field()
    field.fit(training_pages(n, seed))
    return field


def main_text(page: str, field: Field) -> str:
    found = blocks(page)
    score = field.scores([features(b) for b in found])
    return " ".join(b.text for b, y in zip(found, field.decode(score)) if y)


def extract(pages: DataFrame, field: Field, html: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """keep columns, text and n_chars of every row."""
    sent = pages.sparkSession.sparkContext.broadcast(field)
    source = pages.select(*keep, F.col(html).alias("_html"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "_html", 4 << 20):
            texts = [main_text(x or "", sent.value) for x in batch.column(len(keep)).to_pylist()]
            columns = [*(batch.column(i) for i in range(len(keep))), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, names=[*keep, "text", "n_chars"])

    kinds = ", ".join(f"{c} {pages.schema[c].dataType.simpleString()}" for c in keep)
    return source.mapInArrow(run, f"{kinds}, text string, n_chars bigint")


def op7_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"), trained())


QUERIES = {"op7_html_text": op7_html_text}
ORACLES: dict[str, str] = {}
