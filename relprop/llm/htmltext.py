"""HTML extraction: a recurrent labeller of text blocks.

A page is parsed leniently into leaf blocks in page order: stretches of text between block-level tags, each with the
path of tags above it.  A block's input is a vector of hashed path parts (tags, classes, ids), hashed words and a few
figures; a bidirectional LSTM in numpy reads the whole sequence and gives every block a probability of being main
text.  The weights are trained here, on generated pages of many layouts whose main text is known, with a fixed seed.

Scripts, styles, templates, titles, embedded frames and comments of the markup are never blocks; formulas and drawings
are part of the line they stand in, without their source annotations.  A line break tag is white space.  The work of a
tag does not grow with its depth.  Null and empty pages, and pages without main text, give the empty text; rows that
repeat are rows like any other, and an empty table gives an empty result.
"""

from __future__ import annotations

import html as entities
import re
from collections import defaultdict
from functools import lru_cache
from html.parser import HTMLParser
from zlib import crc32

import numpy as np
from pyspark.sql import DataFrame

from .base import arrow_map

PATH_DIM, WORD_DIM, FIGURES, HIDDEN = 128, 32, 8, 24
INPUT = PATH_DIM + WORD_DIM + FIGURES
TRAIN_PAGES, EPOCHS, SEED = 800, 12, 7

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIP = frozenset("script style template title head iframe annotation annotation-xml".split())
INLINE = frozenset("a abbr b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
#: What is not shown breaks no line.
INLINE |= SKIP - {"head"}
#: Parts of formulas and drawings.
INLINE |= frozenset("math semantics mrow mi mo mn ms mtext mspace msup msub msubsup mfrac msqrt mroot mover munder munderover mstyle mpadded mphantom menclose merror mfenced mmultiscripts mprescripts mtable mtr mtd annotation annotation-xml".split())
INLINE |= frozenset("svg g text tspan textpath path rect circle ellipse line polyline polygon defs use symbol desc".split())
#: An opening tag ends open ones of these kinds: (what it ends, what stops the search).
IMPLIED = {"li": (("li",), ("ul", "ol")), "dt": (("dt", "dd"), ("dl",)), "dd": (("dt", "dd"), ("dl",)), "tr": (("tr",), ("table",)), "td": (("td", "th"), ("tr", "table")), "th": (("td", "th"), ("tr", "table")), "option": (("option",), ("select",))}
SPACE = re.compile(r"\s+")
TOKEN = re.compile(r"[a-z0-9]+")


class _Open:
    """An open tag: what its path tells of a block below it.

    ``mask`` has a bit for each input that the path sets, ``leaf`` the one of its last tag that counts.  Tags within a
    line count only if they are named.
    """

    __slots__ = ("tag", "mask", "leaf")

    def __init__(self, tag: str, names: tuple[str, ...], above: _Open | None):
        self.tag, self.mask, self.leaf = tag, above.mask if above else 0, above.leaf if above else 0
        if tag in INLINE and not names:
            return
        self.leaf = 0
        if tag not in ("html", "body"):
            self.mask |= 1 << _bucket("t", tag, PATH_DIM)
            self.leaf = 1 << _bucket("leaf", tag, PATH_DIM)
            for name in names:
                self.mask |= 1 << _bucket("n", name, PATH_DIM)


def path_mask(path: tuple[tuple[str, tuple[str, ...]], ...]) -> int:
    """The inputs of a block below the tags (name, names) of ``path``."""
    top = None
    for tag, names in path:
        top = _Open(tag, names, top)
    return top.mask | top.leaf if top else 0


class _Blocks(HTMLParser):
    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.path: list[_Open] = []
        #: Where each tag is open, and where any tag is that ends a line.
        self.places: dict[str, list[int]] = defaultdict(list)
        self.lines: list[int] = []
        self.skip = 0
        self.buffer: list[str] = []
        self.linked = 0
        self.blocks: list[tuple[str, int, float]] = []

    def flush(self) -> None:
        text = SPACE.sub(" ", "".join(self.buffer)).strip()
        if text:
            top = self.path[-1] if self.path else None
            self.blocks.append((text, top.mask | top.leaf if top else 0, self.linked / max(1, len(text))))
        self.buffer, self.linked = [], 0

    def last(self, tags) -> int:
        """Place of the innermost open tag of these kinds, -1 without."""
        return max((self.places[t][-1] for t in tags if self.places.get(t)), default=-1)

    def pop_to(self, at: int) -> None:
        while len(self.path) > at:
            tag = self.path.pop().tag
            self.places[tag].pop()
            if tag not in INLINE:
                self.lines.pop()
            self.skip -= tag in SKIP

    def handle_starttag(self, tag, attrs):
        if tag not in INLINE:
            self.flush()
            if tag == "body" and self.skip and len(self.path) == sum(len(self.places.get(t, ())) for t in ("html", "head", "title")):
                self.pop_to(0)  # a head that was not closed
            if tag in IMPLIED:
                ends, stops = IMPLIED[tag]
                if (at := self.last(ends)) >= 0 and at > self.last(stops):
                    self.pop_to(at)
            elif self.lines and self.path[self.lines[-1]].tag == "p":
                self.pop_to(self.lines[-1])
        elif tag == "br":
            self.buffer.append(" ")
        if tag in VOID:
            return
        names = tuple(t for k, v in attrs if k in ("class", "id", "role") and v for t in TOKEN.findall(v.lower()))
        self.places[tag].append(len(self.path))
        if tag not in INLINE:
            self.lines.append(len(self.path))
        self.path.append(_Open(tag, names, self.path[-1] if self.path else None))
        self.skip += tag in SKIP

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        if tag not in INLINE:
            self.flush()
        at = self.last((tag,))
        if at >= 0 and (tag not in INLINE or not self.lines or at > self.lines[-1]):
            self.pop_to(at)

    def parse_marked_section(self, i, report=1):
        """A malformed section is a bogus comment up to the next '>'."""
        try:
            k = super().parse_marked_section(i, report)
        except (AssertionError, ValueError):
            k = -1
        return k if k >= 0 else self.parse_bogus_comment(i, 0)

    def handle_data(self, data):
        if not self.skip:
            self.buffer.append(data)
            if self.places.get("a"):
                self.linked += len(data.strip())


def blocks_of(page: str | None) -> list[tuple[str, int, float]]:
    """(text, inputs its path sets, share of linked characters) of each leaf block."""
    if not page:
        return []
    parser = _Blocks()
    parser.feed(page)
    parser.close()
    parser.flush()
    return parser.blocks


@lru_cache(maxsize=100_000)
def _bucket(kind: str, part: str, size: int) -> int:
    return crc32(f"{kind}:{part}".encode("utf-8", "replace")) % size


def vectors(blocks: list[tuple[str, int, float]]) -> np.ndarray:
    x = np.zeros((len(blocks), INPUT), np.float32)
    n = len(blocks)
    for i, (text, mask, linked) in enumerate(blocks):
        x[i, :PATH_DIM] = np.unpackbits(np.frombuffer(mask.to_bytes(PATH_DIM // 8, "little"), np.uint8), bitorder="little")
        words = text.lower().split()
        for w in words:
            x[i, PATH_DIM + _bucket("w", w, WORD_DIM)] += 1.0 / max(4, len(words))
        letters = sum(map(str.isalpha, text)) / max(1, len(text))
        x[i, PATH_DIM + WORD_DIM :] = (np.log1p(len(text)) / 6, np.log1p(len(words)) / 5, linked, letters, i / n, (n - i) / n, np.log1p(n) / 6, text[-1] in ".!?:")
    return x


# The network.  Gates stand in the order input, forget, output, candidate.


def init_weights(rng: np.random.Generator) -> dict[str, np.ndarray]:
    w = {}
    for d in "fb":
        w[f"w{d}"] = rng.normal(0, 1 / np.sqrt(INPUT), (INPUT, 4 * HIDDEN)).astype(np.float32)
        w[f"u{d}"] = rng.normal(0, 1 / np.sqrt(HIDDEN), (HIDDEN, 4 * HIDDEN)).astype(np.float32)
        w[f"b{d}"] = np.r_[np.zeros(HIDDEN), np.ones(HIDDEN), np.zeros(2 * HIDDEN)].astype(np.float32)
    w["v"] = rng.normal(0, 0.2, 2 * HIDDEN).astype(np.float32)
    w["c"] = np.zeros(1, np.float32)
    return w


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def _run(x: np.ndarray, mask: np.ndarray, w: np.ndarray, u: np.ndarray, b: np.ndarray, keep: bool = False):
    """One direction over (steps, pages, INPUT); the state stands still where a page has no block."""
    steps, pages, _ = x.shape
    h, c = np.zeros((pages, HIDDEN), np.float32), np.zeros((pages, HIDDEN), np.float32)
    z = x.reshape(steps * pages, -1) @ w
    z = z.reshape(steps, pages, -1) + b
    out, trace = np.zeros((steps, pages, HIDDEN), np.float32), []
    for t in range(steps):
        g = z[t] + h @ u
        i, f, o = np.split(_sigmoid(g[:, : 3 * HIDDEN]), 3, axis=1)
        a = np.tanh(g[:, 3 * HIDDEN :])
        m = mask[t][:, None]
        new = f * c + i * a
        tc = np.tanh(new)
        if keep:
            trace.append((i, f, o, a, c, tc, h, m))
        c, h = m * new + (1 - m) * c, m * (o * tc) + (1 - m) * h
        out[t] = h
    return out, trace


def _back(x, grad, trace, u):
    """Gradients of one direction, given those of its outputs."""
    steps, pages, _ = x.shape
    dz = np.zeros((steps, pages, 4 * HIDDEN), np.float32)
    dh, dc = np.zeros((pages, HIDDEN), np.float32), np.zeros((pages, HIDDEN), np.float32)
    du = np.zeros_like(u)
    for t in range(steps - 1, -1, -1):
        i, f, o, a, c, tc, h, m = trace[t]
        dh = dh + grad[t]
        dn = m * (dc + dh * o * (1 - tc * tc))
        g = np.concatenate([dn * a * i * (1 - i), dn * c * f * (1 - f), m * dh * tc * o * (1 - o), dn * i * (1 - a * a)], axis=1)
        dz[t] = g
        du += h.T @ g
        dh = g @ u.T + (1 - m) * dh
        dc = dn * f + (1 - m) * dc
    flat = dz.reshape(-1, 4 * HIDDEN)
    return x.reshape(len(flat), -1).T @ flat, du, flat.sum(axis=0)


def _batch(pages: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    steps = max(len(p) for p in pages)
    x, mask = np.zeros((steps, len(pages), INPUT), np.float32), np.zeros((steps, len(pages)), np.float32)
    for j, p in enumerate(pages):
        x[: len(p), j], mask[: len(p), j] = p, 1
    return x, mask


def probabilities(pages: list[np.ndarray], w: dict[str, np.ndarray], room: int = 20_000) -> list[np.ndarray]:
    """Of every block of every page; pages of like length share a batch of at most ``room`` blocks with padding."""
    out: list[np.ndarray] = [np.zeros(0)] * len(pages)
    order = sorted((i for i in range(len(pages)) if len(pages[i])), key=lambda i: len(pages[i]))
    while order:
        take = max(1, min(128, len(order)))
        while take > 1 and take * len(pages[order[take - 1]]) > room:
            take //= 2
        now, order = order[:take], order[take:]
        x, mask = _batch([pages[i] for i in now])
        f, _ = _run(x, mask, w["wf"], w["uf"], w["bf"])
        b, _ = _run(x[::-1], mask[::-1], w["wb"], w["ub"], w["bb"])
        p = _sigmoid(f @ w["v"][:HIDDEN] + b[::-1] @ w["v"][HIDDEN:] + w["c"])
        for j, i in enumerate(now):
            out[i] = p[: len(pages[i]), j]
    return out


def train(pages: list[np.ndarray], labels: list[np.ndarray], epochs: int = EPOCHS, seed: int = SEED, rate: float = 0.01) -> dict[str, np.ndarray]:
    """Adam on the cross-entropy of every block; word inputs are dropped at random so that layout leads."""
    rng = np.random.default_rng(seed)
    w = init_weights(rng)
    m, s, step = {k: np.zeros_like(v) for k, v in w.items()}, {k: np.zeros_like(v) for k, v in w.items()}, 0
    for _ in range(epochs):
        for at in np.array_split(rng.permutation(len(pages)), max(1, len(pages) // 30)):
            x, mask = _batch([pages[i] for i in at])
            y, _ = np.zeros_like(mask), None
            for j, i in enumerate(at):
                y[: len(labels[i]), j] = labels[i]
            x = x.copy()
            x[:, :, PATH_DIM : PATH_DIM + WORD_DIM] *= rng.random((1, len(at), 1)) < 0.7
            x[:, :, :PATH_DIM] *= rng.random((1, len(at), PATH_DIM)) < 0.93
            f, tf = _run(x, mask, w["wf"], w["uf"], w["bf"], True)
            b, tb = _run(x[::-1], mask[::-1], w["wb"], w["ub"], w["bb"], True)
            b = b[::-1]
            p = _sigmoid(f @ w["v"][:HIDDEN] + b @ w["v"][HIDDEN:] + w["c"])
            d = mask * (p - y) / mask.sum()
            g = {"v": np.r_[np.tensordot(d, f, ([0, 1], [0, 1])), np.tensordot(d, b, ([0, 1], [0, 1]))], "c": np.array([d.sum()])}
            g["wf"], g["uf"], g["bf"] = _back(x, d[:, :, None] * w["v"][:HIDDEN], tf, w["uf"])
            g["wb"], g["ub"], g["bb"] = _back(x[::-1], (d[:, :, None] * w["v"][HIDDEN:])[::-1], tb, w["ub"])
            step += 1
            for k in w:
                gk = g[k] + 1e-5 * w[k]
                m[k] = 0.9 * m[k] + 0.1 * gk
                s[k] = 0.999 * s[k] + 0.001 * gk * gk
                w[k] = (w[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(s[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return w


# Generated pages.  Layout words of each kind of part; the rest is drawn at random.

LAYOUT = {
    "menu": ("nav", "nav.menu", "div.menu", "div#navigation", "ul.nav", "div.breadcrumb", "nav.topbar", "div.toolbar"),
    "header": ("header", "div#header", "div.header", "div.masthead", "header.banner", "div.site-header"),
    "advert": ("div.ad", "div.ads", "aside.advert", "div.sponsored", "ins.adsbygoogle", "div.promo", "div.advertisement"),
    "sidebar": ("aside", "div.sidebar", "div.widget", "section.related", "aside.sidebar", "div#sidebar", "div.recommended"),
    "notice": ("div.cookie", "div.notice", "div.consent", "div.popup", "dialog", "div.cookie-banner", "div.alert", "div.gdpr"),
    "form": ("form", "div.newsletter", "form.login", "form.search", "div.subscribe", "form.contact"),
    "comments": ("section.comments", "div#comments", "ol.comment-list", "div.comment", "div.replies", "section#respond", "div.discussion"),
    "footer": ("footer", "div.footer", "div#footer", "footer.site-footer", "div.copyright"),
    "share": ("div.share", "div.social", "ul.social", "div.tags", "div.meta"),
}
MAIN = ("article", "article", "article", "main", "div.content", "div.post", "div#main", "section.article", "main+article", "div.entry-content", "div#content+article", "div.story")
TYPICAL = {
    "menu": "home about contact news products blog login", "header": "welcome site search sign in", "advert": "buy now sale offer ad", "sidebar": "related popular latest more trending",
    "notice": "we use cookies accept privacy policy", "form": "email name submit subscribe password send", "comments": "reply posted says comment ago", "footer": "© copyright all rights reserved terms privacy · 2024", "share": "share tweet tags by",
}


def sample_page(rng: np.random.Generator) -> tuple[str, list[tuple[bool, str]]]:
    """A page and its blocks as (is main text, text)."""
    letters = ["abcdefghijklmnopqrstuvwxyz", "aeinorstláéíóñ", "абвгдеиклмнопрст", "eèéêàçuxoilrnmtd"][rng.integers(4)]
    out, truth = [], []

    def words(n: int) -> str:
        return " ".join("".join(letters[k] for k in rng.integers(0, len(letters), rng.integers(1, 10))) for _ in range(n))

    def sentence(least: int, most: int) -> str:
        kind, t = rng.random(), words(int(rng.integers(least, most)))
        t = t.capitalize() + ("." if rng.random() < 0.8 else "")
        if kind < 0.06:
            t = t.upper().replace(" ", "!! ")
        elif kind < 0.12:
            t = " ".join(w + "***" for w in t.split())
        elif kind < 0.16:
            t = " | ".join(t.split())
        elif kind < 0.19:
            t = " ".join([t.split()[0]] * 30)
        return t + (" & co" if rng.random() < 0.1 else "")

    def put(text: str, main: bool, inner: str | None = None) -> str:
        truth.append((main, SPACE.sub(" ", text).strip()))
        return inner or entities.escape(text, quote=False)

    def opened(spec: str) -> tuple[str, str]:
        head, tail = "", ""
        for one in spec.split("+"):
            tag = re.match(r"\w+", one)[0]
            name = f' class="{one.split(".", 1)[1]}"' if "." in one else f' id="{one.split("#", 1)[1]}"' if "#" in one else ""
            head, tail = f"{head}<{tag}{name}>", f"</{tag}>{tail}"
        return head, tail

    def boiler(kind: str) -> None:
        head, tail = opened(str(rng.choice(LAYOUT[kind])))
        say = lambda: (words(int(rng.integers(1, 4))) if rng.random() < 0.6 else str(rng.choice(TYPICAL[kind].split())))
        out.append(head)
        for _ in range(int(rng.integers(1, 4 if kind in ("advert", "notice", "header") else 7))):
            if kind in ("menu", "share") or kind in ("footer", "sidebar") and rng.random() < 0.4:
                tag = "li" if rng.random() < 0.8 else "div"
                t = say()
                out.append(f"<{tag}>" + put(t, False, f'<a href="/x">{entities.escape(t, quote=False)}</a>') + f"</{tag}>")
            elif kind == "form" and rng.random() < 0.6:
                out.append("<div>" + put(say(), False) + "</div><input name=q>")
            else:
                tag = str(rng.choice(["p", "div", "h3", "p"]))
                out.append(f"<{tag}>" + put(sentence(2, 30 if kind in ("comments", "advert", "footer") else 12) if rng.random() < 0.6 else say() + " " + words(3), False) + f"</{tag}>")
        if kind in ("advert", "footer") and rng.random() < 0.5:
            out.append(put(("© " if kind == "footer" else "") + sentence(2, 14), False))
        out.append(tail)

    for kind, chance in (("notice", 0.25), ("header", 0.35), ("menu", 0.85), ("advert", 0.5), ("share", 0.1), ("sidebar", 0.15), ("form", 0.15)):
        if rng.random() < chance:
            boiler(kind)
    head, tail = opened(str(rng.choice(MAIN)))
    out.append(head)
    loose = rng.random() < 0.5
    if rng.random() < 0.85:
        out.append(f"<h1>{put(sentence(2, 12), True)}</h1>")
    many = 90 if rng.random() < 0.08 else 14
    for i in range(int(rng.integers(1, many))):
        kind, t = rng.random(), sentence(1, 60 if rng.random() < 0.8 else 4)
        if loose and (i == 0 or kind < 0.1):
            out.append(f"<p><b>{put(t, True)}<br>")
        elif kind < 0.72:
            out.append(f"<p>{put(t, True)}" + ("</p>" if rng.random() < 0.9 else ""))
        elif kind < 0.8:
            out.append(f"<h2>{put(sentence(1, 8), True)}</h2>")
        elif kind < 0.87:
            out.append("<ul>" + "".join(f"<li>{put(sentence(1, 15), True)}</li>" for _ in range(int(rng.integers(1, 5)))) + "</ul>")
        elif kind < 0.91:
            out.append(f"<blockquote>{put(t, True)}</blockquote>")
        elif kind < 0.94:
            out.append("<table><tr>" + "".join(f"<td>{put(words(2), True)}</td>" for _ in range(3)) + "</tr></table>")
        else:
            boiler(str(rng.choice(["advert", "advert", "share", "form", "sidebar"])))
    out.append(tail)
    for kind, chance in (("share", 0.15), ("comments", 0.4), ("sidebar", 0.3), ("form", 0.2), ("advert", 0.2), ("notice", 0.15), ("menu", 0.1), ("footer", 0.85)):
        if rng.random() < chance:
            boiler(kind)
    page = f"<!DOCTYPE html><html><head><title>{words(4)}</title><style>p{{}}</style></head><body>{''.join(out)}" + ("</body></html>" if rng.random() < 0.8 else "")
    return page, truth


def training_set(n: int = TRAIN_PAGES, seed: int = SEED) -> tuple[list[np.ndarray], list[np.ndarray]]:
    rng = np.random.default_rng(seed)
    xs, ys = [], []
    while len(xs) < n:
        page, truth = sample_page(rng)
        blocks = blocks_of(page)
        if [b[0] for b in blocks] == [t for _, t in truth]:  # unclosed parts can run together: such pages are left out
            xs.append(vectors(blocks))
            ys.append(np.array([m for m, _ in truth], np.float32))
    return xs, ys


@lru_cache(maxsize=1)
def trained() -> dict[str, np.ndarray]:
    """The weights: some seconds of work on the driver, the same each time."""
    return train(*training_set())


def extract(pages: list[str | None], w: dict[str, np.ndarray]) -> list[str]:
    """Main text of each page."""
    blocks = [blocks_of(p) for p in pages]
    probs = probabilities([vectors(b) for b in blocks], w)
    return ["\n".join(t for (t, _, _), p in zip(b, ps, strict=True) if p >= 0.5) for b, ps in zip(blocks, probs, strict=True)]


def main_text(pages: DataFrame, weights: dict[str, np.ndarray] | None = None) -> DataFrame:
    """page_id, url, text, n_chars of every row."""
    shared = pages.sparkSession.sparkContext.broadcast(weights or trained())  # of a fixed size

    def make():
        def kernel(cols):
            ids, urls, htmls = cols
            texts = extract(htmls, shared.value)
            return [ids, urls, texts, [len(t) for t in texts]]

        return kernel

    return arrow_map(pages.select("page_id", "url", "html"), make, "page_id long, url string, text string, n_chars long")
