"""Main text of web pages: gradient-boosted trees over DOM-node features, decoded over the tree.

A tolerant parser builds the tree of block elements; every block gets features of its subtree (text, link and markup
density), its own and its ancestors' attribute tokens, its depth, and its siblings. Trees fitted on generated pages
give each block the odds of holding article text. The decoding takes the best choice over the whole tree under the
rule that a kept block has kept ancestors, so no kept block lies under a dropped one.
"""

from __future__ import annotations

import functools
import html as entities
import random
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from slicecode.llm.common import slices_by_bytes

INLINE = frozenset("a abbr acronym b bdi bdo big cite code data dfn em font i img ins del kbd mark q s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose content is no text of the page: scripts, styles, markup kept for scripts, the document's head, fields of forms.
SILENT = frozenset("script style template iframe head title textarea select option".split())
RAW = frozenset("script style textarea title iframe".split())
SCOPES = frozenset("article aside body div footer form header html main nav section table td th blockquote".split())
CLOSES = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("td", "th", "tr"), "td": ("td", "th"), "th": ("td", "th"), "thead": ("tr",), "tbody": ("tr", "thead"), "tfoot": ("tr", "tbody")}
_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^'\">])*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)", re.DOTALL)
_ATTR = re.compile(r"\b(class|id|role|itemprop|aria-label)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.IGNORECASE)
_TOKEN = re.compile(r"[A-ZÀ-Þ]?[a-zß-ÿ]+|[A-ZÀ-Þ]+")

#: Attribute tokens by what they tell (fixed values).
FAMILIES = {
    "content": "article content main post entry story text body page blog paragraph maincontent articlebody prose",
    "nav": "nav menu navbar navigation breadcrumb breadcrumbs links toc pagination pager tabs skip dropdown",
    "header": "header masthead banner top hero logo brand topbar head",
    "footer": "footer foot copyright legal bottom colophon imprint",
    "side": "sidebar side aside widget widgets rail related recommended more trending popular also teaser",
    "ad": "ad ads advert adverts advertisement advertising sponsor sponsored promo promoted promotion adsense partner commercial",
    "social": "share sharing social follow tweet facebook twitter like buttons print",
    "comment": "comment comments reply replies discussion disqus respond reader readers feedback responses commentlist thread",
    "notice": "cookie cookies consent gdpr notice notification alert popup modal overlay paywall subscribe subscription newsletter signup warning disclaimer toast announcement",
    "form": "form search login input field poll survey contact register",
    "meta": "meta author byline date tags category caption info timestamp figure",
}
FAMILY_OF = {w: k for k, words in enumerate(FAMILIES.values()) for w in words.split()}
N_FAMILIES = len(FAMILIES)
#: Beginnings of such words in the languages of the corpus (fixed values); those of six letters or more count anywhere in a word.
STEMS = {
    "content": "articl artikel inhalt beitrag haupt contenu conteni principal corps cuerpo texte texto maincont",
    "nav": "navig menü menú brotkr krümel migas sommaire índice breadcrumb",
    "header": "kopfz kopfb seitenkopf entête entete cabecera encabez bandeau masthead pageheader",
    "footer": "fußz fussz fußb fussb pied piedepag impressum mentionsleg avisoleg pagefooter sitefooter",
    "side": "seitenl randsp barrelat barralat lateral verwandt ähnlich aehnlich connexe relacion related sidebar empfehl recomend recommand",
    "ad": "werb anzeige reklame publicit publicid anunci patrocin gesponser advert sponsor",
    "social": "teilen partag compart sozial share",
    "comment": "kommentar commentair comentari comment leser lecteur lector antwort répons repons respuest meinung diskussion discusi opinion",
    "notice": "hinweis meldung benachr warnung avertiss newsletter rundbrief boletin boletín abonn suscri cookie consent einwillig",
    "form": "formul suche recherch buscar búsqueda busqueda umfrage encuesta sondage kontakt contacto anmeld inscri",
    "meta": "autor auteur datum fecha schlagw etiquet bildunter légende leyenda",
}
_STEMS = sorted(((stem, list(FAMILIES).index(name)) for name, stems in STEMS.items() for stem in stems.split()), key=lambda x: -len(x[0]))


@functools.lru_cache(1 << 16)
def family_of(token: str) -> int | None:
    """The family of an attribute token in lower case: by the whole word, by its beginning, by a long stem in it."""
    if token in FAMILY_OF:
        return FAMILY_OF[token]
    return next((k for fits in (lambda stem: token.startswith(stem), lambda stem: len(stem) > 5 and stem in token) for stem, k in _STEMS if fits(stem)), None)


#: Groups of tags that features tell apart.
TAG_GROUPS = {t: k for k, ts in enumerate(("p", "h1 h2 h3 h4 h5 h6 hgroup", "li", "ul ol dl menu", "article main", "nav", "header", "footer", "aside", "form button label fieldset dialog", "section", "div", "table tbody thead tr td th", "blockquote pre figure figcaption dd dt details summary address", "body html")) for t in ts.split()}
N_GROUPS = 16


@dataclass(slots=True)
class Block:
    tag: str
    parent: int
    depth: int
    start: int
    families: int = 0
    silent: bool = False
    end: int = 0
    order: int = 0  # among its siblings
    children: int = 0
    own: int = 0  # characters of its own text
    links: int = 0
    words: int = 0
    stops: int = 0
    blocks: int = 0  # in the subtree
    p: int = 0
    text: int = 0  # of the subtree
    linked: int = 0


def parse(page: str) -> tuple[list[Block], list[tuple[int, str, bool]]]:
    """(blocks in document order, texts): a text has its block, its decoded characters, and if a block border or a line
    break lies before it. Anything that is cut off at the end of the page is closed there."""
    blocks = [Block("html", -1, 0, 0)]
    stack, texts, broken, link = [0], [], True, False
    at, n, find = 0, len(page), _TAG.search

    def say(raw: str) -> None:
        nonlocal broken
        if not raw:
            return
        k = stack[-1]
        b = blocks[k]
        if b.silent:
            return
        text = entities.unescape(raw) if "&" in raw else raw
        words = text.split()
        if words:
            size = sum(map(len, words))
            b.own += size
            b.words += len(words)
            b.stops += text.count(".") + text.count(",")
            if link:
                b.links += size
        elif not text:
            return
        texts.append((k, text, broken))
        broken = False

    def close(position: int, to: int) -> None:
        while len(stack) > to:
            blocks[stack.pop()].end = position

    while at < n:
        m = find(page, at)
        if not m:
            say(page[at:])
            break
        say(page[at : m.start()])
        at = m.end()
        name = m[2] or m[5]
        if not name:
            continue
        tag, closing = name.lower(), bool(m[1] or m[4])
        if tag in INLINE:
            if tag == "a":
                link = not closing
            continue
        broken = True
        if tag == "br":
            continue
        link = False
        if closing:
            for i in range(len(stack) - 1, 0, -1):
                t = blocks[stack[i]].tag
                if t == tag:
                    close(m.start(), i)
                    break
                if tag in ("p", "li", "dt", "dd", "h1", "h2", "h3", "h4", "h5", "h6") and t in SCOPES:
                    break
            continue
        for i in range(len(stack) - 1, 0, -1):  # what the new element ends
            t = blocks[stack[i]].tag
            if t == "p" or t in CLOSES.get(tag, ()):
                close(m.start(), i)
            elif t in SCOPES or t in ("ul", "ol", "dl", "tbody", "thead") or tag not in CLOSES:
                break
        if tag in VOID:
            continue
        raw_attrs = m[3] if m[2] else m[6]
        parent = blocks[stack[-1]]
        b = Block(tag, stack[-1], parent.depth + 1, m.start(), order=parent.children, silent=parent.silent or tag in SILENT)
        parent.children += 1
        if raw_attrs and not b.silent:
            for a in _ATTR.finditer(raw_attrs):
                for w in _TOKEN.findall(a[2] or a[3] or a[4] or ""):
                    k = family_of(w.lower())
                    if k is not None:
                        b.families |= 1 << k
        blocks.append(b)
        stack.append(len(blocks) - 1)
        if tag in RAW and not (raw_attrs or "").endswith("/"):
            shut = re.compile(rf"</{tag}\b[^>]*>", re.IGNORECASE).search(page, at)
            close(shut.start() if shut else n, len(stack) - 1)
            at = shut.end() if shut else n
    close(n, 0)
    for b in reversed(blocks):
        b.text += b.own
        b.linked += b.links
        if b.parent >= 0:
            up = blocks[b.parent]
            up.text += b.text
            up.linked += b.linked
            up.blocks += b.blocks + 1
            up.p += b.p + (b.tag == "p")
    return blocks, texts


def features(blocks: list[Block]) -> np.ndarray:
    """One row for each block."""
    n = len(blocks)
    total, size = max(blocks[0].text, 1), max(blocks[0].end, 1)
    rows, up_families, up_groups, near, shaped = [], [0] * n, [0] * n, [0] * n, [0] * n
    before: dict[int, Block] = {}
    alike = Counter((b.parent, b.tag, b.families, min(b.blocks, 6)) for b in blocks)
    for k, b in enumerate(blocks):
        group = TAG_GROUPS.get(b.tag, 15)
        up = blocks[b.parent] if b.parent >= 0 else b
        up_families[k] = (up_families[b.parent] | up.families) if k else 0
        up_groups[k] = (up_groups[b.parent] | 1 << TAG_GROUPS.get(up.tag, 15)) if k else 0
        near[k] = (b.families or near[b.parent]) if k else b.families  # of the nearest block that has any
        last = before.get(b.parent)
        before[b.parent] = b
        shaped[k] = alike[b.parent, b.tag, b.families, min(b.blocks, 6)] if b.blocks else 0  # siblings of the same make
        text, inside = b.text, max(b.end - b.start, 1)
        rows.append(
            [group, b.families, up_families[k], up_groups[k], near[k], b.depth, b.order, up.children, b.order / max(up.children, 1), text, b.own, b.words, text / inside, b.linked / max(text, 1), b.links / max(b.own, 1), b.stops / max(b.words, 1), b.blocks, b.p, text / max(b.blocks + 1, 1), b.start / size, text / total, text / max(up.text, 1), up.linked / max(up.text, 1), up.text / max(up.blocks, 1), last.text if last else -1, last.linked / max(last.text, 1) if last else -1, shaped[k], shaped[b.parent] if k else 0]
        )
    raw = np.array(rows, np.float32)
    bits = [(raw[:, c].astype(np.int64)[:, None] >> np.arange(w)) & 1 for c, w in ((1, N_FAMILIES), (2, N_FAMILIES), (3, N_GROUPS), (4, N_FAMILIES))]
    hot = raw[:, :1].astype(np.int64) == np.arange(N_GROUPS)
    return np.concatenate([hot, *bits, raw[:, 5:]], axis=1).astype(np.float32)


@dataclass
class Boosted:
    """Depth-wise trees over binned features: arrays tree x node; a node without a split sends everything left."""

    edges: list[np.ndarray]
    feature: np.ndarray
    bound: np.ndarray
    leaf: np.ndarray
    start: float

    def margin(self, x: np.ndarray) -> np.ndarray:
        bins = np.stack([np.searchsorted(e, x[:, f], side="left") for f, e in enumerate(self.edges)], axis=1).astype(np.int16)
        out, rows = np.full(len(x), self.start), np.arange(len(x))
        depth = int(np.log2(self.leaf.shape[1]))
        for feature, bound, leaf in zip(self.feature, self.bound, self.leaf, strict=True):
            at = np.zeros(len(x), np.int64)
            for _ in range(depth):
                at = 2 * at + 1 + (bins[rows, feature[at]] > bound[at])
            out += leaf[at - (leaf.size - 1)]
        return out


def boost(x: np.ndarray, y: np.ndarray, rounds: int = 40, depth: int = 5, rate: float = 0.25, bins: int = 32, ridge: float = 1.0, least: float = 5.0) -> Boosted:
    """Newton boosting of the logistic loss; splits by gain over histograms of quantile bins."""
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for f in range(x.shape[1])]
    coded = np.stack([np.searchsorted(e, x[:, f], side="left") for f, e in enumerate(edges)], axis=1)
    n_nodes, b = 2**depth - 1, bins + 1
    share = y.mean()
    start = float(np.log(share / (1 - share)))
    margin, made = np.full(len(y), start), []
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-margin))
        g, h = p - y, p * (1 - p)
        feature, bound = np.zeros(n_nodes, np.int64), np.full(n_nodes, b, np.int64)
        at = np.zeros(len(y), np.int64)
        for level in range(depth):
            first, width = 2**level - 1, 2**level
            local, best = at - first, np.full(width, 1e-6)
            for f, e in enumerate(edges):
                if not len(e):
                    continue
                key = local * b + coded[:, f]
                gs = np.bincount(key, g, width * b).reshape(width, b).cumsum(1)
                hs = np.bincount(key, h, width * b).reshape(width, b).cumsum(1)
                gt, ht = gs[:, -1:], hs[:, -1:]
                gain = gs**2 / (hs + ridge) + (gt - gs) ** 2 / (ht - hs + ridge) - gt**2 / (ht + ridge)
                gain[(hs < least) | (ht - hs < least)] = 0
                k = gain.argmax(1)
                top = gain[np.arange(width), k]
                better = top > best
                best[better], feature[first : first + width][better], bound[first : first + width][better] = top[better], f, k[better]
            at = 2 * at + 1 + (coded[np.arange(len(y)), feature[at]] > bound[at])
        local = at - n_nodes
        gs, hs = np.bincount(local, g, n_nodes + 1), np.bincount(local, h, n_nodes + 1)
        leaf = -rate * gs / (hs + ridge)
        margin += leaf[local]
        made.append((feature, bound, leaf))
    return Boosted(edges, np.stack([m[0] for m in made]), np.stack([m[1] for m in made]), np.stack([m[2] for m in made]), start)


# --- generated training pages -------------------------------------------------------------------------------------

_WORDS = {lang: s.split() for lang, s in {"a": "the of and in on er th an re ti en at es or st ing ed ion ble ly sh wh", "b": "de la le que eau ou ai en é ré è ment tion pa vi eux", "c": "der die und ein sch ung heit keit ver ge be ach zu ü ö", "d": "de la os as ción que mente do ra ez ja ll ñ ía"}.items()}
MARK = "⁠"  # put at the start of article text while labels are drawn up


class PageMaker:
    """Random pages whose article texts are marked; the same seed gives the same pages."""

    def __init__(self, seed: int) -> None:
        self.r = random.Random(seed)

    def prose(self, least: int, most: int) -> str:
        r, out = self.r, []
        syllables = _WORDS[r.choice("abcd")]
        for _ in range(r.randint(least, most)):
            w = "".join(r.choice(syllables) for _ in range(r.choice((1, 1, 2, 2, 3))))
            out.append(w + r.choice(("", "", "", "", "", ",", ".")))
        noisy = r.random() < 0.1
        return " ".join(w + (r.choice(("###", "$$$", "&amp;&amp;", "%%%")) if noisy else "") for w in out).capitalize() + r.choice((".", ".", ""))

    def attr(self, *families: str, chance: float = 0.85) -> str:
        r = self.r
        if r.random() > chance:
            return r.choice(("", "", f' class="{self.prose(1, 1)[:6]}{r.randint(1, 99)}"'))
        word = r.choice(FAMILIES[r.choice(families)].split())
        extra = r.choice(("", "", "-wrap", "-box", " clearfix", "_1", "-inner", "Area", " col-8", "-section", "-list", "-container"))
        return f' {r.choice(("class", "class", "id"))}="{word}{extra}"'

    def links(self, least: int, most: int) -> str:
        return "".join(f'<li><a href="/{k}">{self.prose(1, 4)}</a></li>' for k in range(self.r.randint(least, most)))

    def boiler(self, inside: bool) -> str:
        """One block of what is no article text; ``inside``: of the kinds that stand within articles."""
        r = self.r
        kinds = ["ad", "related", "share", "notice", "form", "script", "comments"] + (["aside"] if inside else ["nav", "nav", "header", "footer", "footer", "aside", "sidebar", "crumbs", "hidden", "ad", "notice"])
        kind, box = r.choice(kinds), r.choice(("div", "div", "section", "aside"))
        long = self.prose(4, r.choice((12, 30, 70)))
        if kind == "nav":
            return r.choice((f"<nav{self.attr('nav', chance=0.5)}><ul>{self.links(3, 9)}</ul></nav>", f"<div{self.attr('nav', chance=1)}><ul>{self.links(3, 9)}</ul></div>", f"<ul{self.attr('nav', chance=1)}>{self.links(3, 9)}</ul>"))
        if kind == "header":
            return f"<header{self.attr('header', chance=0.4)}><a href='/'>{self.prose(1, 3)}</a>{r.choice(('', f'<h1>{self.prose(1, 4)}</h1>', f'<p>{self.prose(3, 10)}</p>'))}{r.choice(('', f'<ul>{self.links(2, 6)}</ul>'))}</header>" if r.random() < 0.7 else f"<div{self.attr('header', chance=1)}><p>{self.prose(2, 8)}</p></div>"
        if kind == "footer":
            text = f"&copy; {self.prose(1, 3)} &middot; {self.prose(3, 20)}"
            return r.choice((f"<footer{self.attr('footer', chance=0.4)}>{text}</footer>", f"<footer><p>{text}</p><ul>{self.links(2, 6)}</ul></footer>", f"<div{self.attr('footer', chance=1)}><p>{text}</p></div>"))
        if kind in ("aside", "sidebar"):
            tag = "aside" if kind == "aside" else "div"
            return f"<{tag}{self.attr('side', chance=0.5 if tag == 'aside' else 1)}><h3>{self.prose(1, 4)}</h3>{r.choice((f'<p>{long}</p>', f'<ul>{self.links(2, 6)}</ul>', long))}</{tag}>"
        if kind == "ad":
            return f"<{box}{self.attr('ad', chance=1)}>{r.choice((long, f'<p>{long}</p>', f'<a href=x>{long}</a>', f'<span>{long}</span>'))}</{box}>"
        if kind == "related":
            return f"<{box}{self.attr('side', chance=1)}><h4>{self.prose(1, 4)}</h4><ul>{self.links(2, 6)}</ul></{box}>"
        if kind == "share":
            return f"<{r.choice(('div', 'ul'))}{self.attr('social', chance=1)}>{self.links(2, 5)}</div>".replace("</div>", "")
        if kind == "notice":
            return f"<{box}{self.attr('notice', chance=1)}>{r.choice((f'<p>{long}</p>', long))}{r.choice(('', '<button>' + self.prose(1, 2) + '</button>'))}</{box}>"
        if kind == "form":
            return f"<form{self.attr('form', chance=0.6)}><label>{self.prose(1, 4)}</label><input name=q>{r.choice(('', f'<p>{long}</p>'))}<button>{self.prose(1, 2)}</button></form>"
        if kind == "crumbs":
            return f"<{r.choice(('ol', 'div', 'p'))}{self.attr('nav', chance=1)}>" + " &gt; ".join(f"<a href=/{k}>{self.prose(1, 2)}</a>" for k in range(r.randint(2, 4))) + "</div>"
        if kind == "hidden":
            return f'<div{self.attr("notice", chance=1)} style="display:none"><p>{long}</p></div>'
        if kind == "script":
            return '<script>var t="</p>";track(1);</script>'
        item = r.choice(("div", "li", "article", "section"))
        each = "".join(f"<{item}{self.attr('comment', chance=0.6)}><b>{self.prose(1, 2)}</b><p>{self.prose(3, r.choice((15, 60)))}</p></{item}>" for _ in range(r.randint(1, 5)))
        list_tag = "ul" if item == "li" else r.choice(("div", "section"))
        return f"<{list_tag}{self.attr('comment', chance=0.95)}>{r.choice(('', f'<h3>{self.prose(1, 3)}</h3>'))}{each}</{list_tag}>"

    def article(self) -> str:
        r, out = self.r, []
        if r.random() < 0.8:
            out.append(f"<h1>{MARK}{self.prose(2, 9)}</h1>")
        if r.random() < 0.25:
            out.append(f"<{r.choice(('p', 'div'))}{self.attr('meta', chance=1)}>{MARK}{self.prose(2, 6)}</p>".replace("</p>", ""))
        for _ in range(r.randint(1, r.choice((3, 8, 20)))):
            x = r.random()
            text = MARK + self.prose(1, r.choice((2, 15, 60, 120)))
            if x < 0.72:
                out.append(f"<p>{r.choice(('', '', '<b>'))}{text}{r.choice(('</p>', '</p>', '</p>', '<br>', ''))}")
            elif x < 0.79:
                out.append(f"<h{r.randint(2, 4)}>{MARK}{self.prose(1, 6)}</h2>".replace("</h2>", "") + "\n")
                out[-1] = re.sub(r"<h(\d)>(.*)", lambda m: f"<h{m[1]}>{m[2].strip()}</h{m[1]}>", out[-1].strip())
            elif x < 0.85:
                tag = r.choice(("ul", "ol"))
                out.append(f"<{tag}>" + "".join(f"<li>{r.choice(('', '<a href=x>'))}{MARK}{self.prose(1, 15)}</li>" for _ in range(r.randint(2, 6))) + f"</{tag}>")
            elif x < 0.9:
                out.append(f"<blockquote>{r.choice(('', '<p>'))}{text}</blockquote>")
            elif x < 0.94:
                out.append("<table>" + "".join(f"<tr><td>{MARK}{self.prose(1, 3)}</td><td>{MARK}{self.prose(1, 3)}</td></tr>" for _ in range(r.randint(1, 5))) + "</table>")
            elif x < 0.97:
                out.append(f"<figure><img src=x><figcaption>{MARK}{self.prose(2, 12)}</figcaption></figure>")
            else:
                out.append(f"<div>{text}</div>")
            if r.random() < 0.07:
                out.append(self.boiler(True))
        return "".join(out)

    def bare(self) -> str:
        """A page whose article has no container of its own, or one that tells nothing; other blocks are few."""
        r = self.r
        text = lambda: f"{MARK}{self.prose(8, r.choice((20, 60, 120)))}"
        parts = [r.choice((f"<p>{text()}</p>", f"<p>{text()}", f"<div>{text()}</div>")) for _ in range(r.choice((1, 1, 2, 2, 3, 5)))]
        core = "".join([f"<h1>{MARK}{self.prose(2, 8)}</h1>"] * (r.random() < 0.3) + parts)
        if r.random() < 0.5:
            core = f"<div{r.choice(('', '', f' id=x{r.randint(1, 99)}'))}>{core}</div>"
        around = [f"<nav>{r.choice((self.prose(2, 8), f'<ul>{self.links(2, 6)}</ul>'))}</nav>", f"<footer>{self.prose(3, 12)}</footer>", f"<header>{self.prose(2, 8)}</header>"]
        return r.choice(("", around[0], around[2])) + core + r.choice(("", "", around[1]))

    def page(self) -> str:
        r = self.r
        if r.random() < 0.2:
            page = self.bare()
            return r.choice((page, f"<html><body>{page}</body></html>"))
        tag = r.choice(("article", "article", "article", "main", "div", "div", "section"))
        attr = self.attr("content", chance=0.3 if tag in ("article", "main") else 0.75)
        core = f"<{tag}{attr}>{self.article()}</{tag}>"
        for _ in range(r.randint(0, 2)):
            wrap = r.choice(("div", "div", "section", "main"))
            core = f"<{wrap}{self.attr('content', chance=0.4)}>{self.boiler(False) if r.random() < 0.2 else ''}{core}{self.boiler(False) if r.random() < 0.2 else ''}</{wrap}>"
        head = f'<!DOCTYPE html><html><head><meta charset="utf-8"><title>{self.prose(2, 8)}</title><style>p{{margin:0}}</style></head><body>'
        return head + "".join(self.boiler(False) for _ in range(r.randint(0, 4))) + core + "".join(self.boiler(False) for _ in range(r.randint(0, 4))) + r.choice(("</body></html>", "</body></html>", ""))


def labelled(page: str) -> tuple[np.ndarray, np.ndarray, str]:
    """(features, label of each block: its subtree has article text, the article text) of a generated page."""
    blocks, texts = parse(page)
    keep = np.zeros(len(blocks), bool)
    for k, text, _ in texts:
        if MARK in text:
            while k >= 0 and not keep[k]:
                keep[k] = True
                k = blocks[k].parent
    blocks, texts = parse(page.replace(MARK, ""))
    own = parse(page)[1]
    marked = {k for k, text, _ in own if MARK in text}
    return features(blocks), keep, assemble([(k, t.replace(MARK, ""), b) for k, t, b in own if k in marked])


def used_blocks(blocks: list[Block]) -> np.ndarray:
    return np.array([b.text > 0 and not b.silent for b in blocks])


@functools.cache
def trained(pages: int = 500, seed: int = 11) -> Boosted:
    """Trees fitted on ``pages`` generated pages."""
    maker = PageMaker(seed)
    xs, ys = [], []
    for _ in range(pages):
        page = maker.page()
        x, y, _ = labelled(page)
        use = used_blocks(parse(page.replace(MARK, ""))[0])
        xs.append(x[use])
        ys.append(y[use])
    return boost(np.concatenate(xs), np.concatenate(ys).astype(float))


# --- decoding -------------------------------------------------------------------------------------------------------


def decode(blocks: list[Block], odds: np.ndarray) -> list[bool]:
    """The best consistent choice: a block's gain is its log odds plus the gains of the children worth keeping; a block is
    kept if its gain is positive and its parent is kept. The root is kept if anything is."""
    gain = [0.0] * len(blocks)
    for k in range(len(blocks) - 1, -1, -1):
        b = blocks[k]
        gain[k] += -1e9 if b.silent else float(odds[k]) if b.text else 0.0
        if b.parent >= 0 and gain[k] > 0:
            gain[b.parent] += gain[k]
    kept = [gain[0] > 0] + [False] * (len(blocks) - 1)
    for k in range(1, len(blocks)):
        kept[k] = kept[blocks[k].parent] and gain[k] > 0
    return kept


def assemble(texts: list[tuple[int, str, bool]]) -> str:
    """Texts in page order: a space at block borders, none inside a block, white space runs as one space."""
    return " ".join("".join((" " if b else "") + t for _, t, b in texts).split())


def extract(pages: list[str | None], model: Boosted) -> list[str]:
    """The main text of each page; the trees see all pages' blocks at once."""
    parsed = [parse(p or "") for p in pages]
    tables = [features(b) for b, _ in parsed]
    odds = np.clip(model.margin(np.concatenate(tables)), -8, 8) if tables else np.zeros(0)
    out, at = [], 0
    for (blocks, texts), x in zip(parsed, tables, strict=True):
        kept = decode(blocks, odds[at : at + len(x)])
        at += len(x)
        said, broken = [], False
        for k, text, b in texts:
            broken |= b
            if kept[k]:
                said.append((k, text, broken))
                broken = False
        out.append(assemble(said))
    return out


def extract_pages(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """One row for each input row: page_id, url, text (empty if none), n_chars (code points).

    A null or empty page has no text. Broken markup is closed at its end. Repeated rows give repeated rows; an empty
    table none. Bounded memory: one slice of a batch at a time.
    """
    sent = pages.sparkSession.sparkContext.broadcast(trained())  # a fixed number of trees
    narrow = pages.select(F.col(page_id).alias("page_id"), F.col(url).alias("url"), F.col(html).cast("string").alias("html"))
    schema = T.StructType([narrow.schema["page_id"], narrow.schema["url"]] + list(T.StructType.fromDDL("text string, n_chars long")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices_by_bytes(whole, 2 << 20):
                texts = extract(batch.column("html").to_pylist(), sent.value)
                yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=schema.names)

    return narrow.mapInArrow(run, schema)
