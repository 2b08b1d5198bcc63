"""Main-text extraction from HTML by a recurrent block labeller.

A page is cut into leaf blocks, the runs of text between block-level tags. Each block is a vector of its tag path
(tags with their class and id words, hashed), of a hashed set of all its words and of a few measures. A bidirectional LSTM
in numpy reads the blocks of a page in order and labels each as main text or not, with the whole page as context.

The network is trained here, on pages built from a grammar of page parts (``training_pages``): running text of frequent
words of four languages and random letters, menus, and notices in the words of their part, some of them in plain tags
amid the text. Nothing is fitted to given pages. Scripts, styles, comments and markup never become blocks.

Defined results: null and empty pages give the empty text; broken markup is read as far as it goes; very long pages are
read whole; repeated rows are alike; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
import zlib
from collections import Counter
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# fixed values: tags by what they do to the text
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section select summary table tbody td template textarea tfoot th thead title tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript svg math iframe object canvas".split())
SELF_CLOSING = {"p": frozenset(["p"]), "li": frozenset(["li"]), "td": frozenset(["td", "th"]), "th": frozenset(["td", "th"]), "tr": frozenset(["tr", "td", "th"]), "option": frozenset(["option"]), "dt": frozenset(["dt", "dd"]), "dd": frozenset(["dt", "dd"])}
SPECIAL = re.compile(r"[>\"']")
TAG = re.compile(r"<(/?)([A-Za-z][A-Za-z0-9:-]*)(.*)>", re.S)
MARKS = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
WORDS = re.compile(r"[a-z]+")
LETTERS = re.compile(r"[^\W\d_]+")
SPACE = re.compile(r"\s+")
RAW_END = {name: re.compile(rf"</{name}\s*>", re.I) for name in RAW}

PATH_DIMS, WORD_DIMS, MEASURES, HIDDEN = 192, 256, 6, 16
DIMS = PATH_DIMS + WORD_DIMS + MEASURES
WORD_DECAY = 2.0
MOST_PATHS = 50_000  # paths remembered between pages


class Block:
    __slots__ = ("path", "linked", "text")

    def __init__(self, path: "Path", text: str, linked: int):
        self.path, self.text, self.linked = path, text, linked


class Path:
    """The open tags down to one, as a sum of hashed slots: a tag adds its own to its parent's, whatever the depth."""

    __slots__ = ("name", "raw", "vector", "below")
    made = 0

    def __init__(self, name: str, raw: np.ndarray):
        self.name, self.raw, self.below = name, raw, {}
        self.vector = np.clip(raw, -2, 2)

    def child(self, name: str, marks: tuple[str, ...]) -> "Path":
        key = (name, marks)
        out = self.below.get(key)
        if out is None:
            raw = self.raw.copy()
            for part in (name, *(f"{name}.{k}" for k in marks), *(f".{k}" for k in marks)):
                for salt in ("path", "more"):
                    i, sign = _slot(f"{salt} {part}", PATH_DIMS)
                    raw[i] += sign
            out = self.below[key] = Path(name, raw)
            Path.made += 1
        return out


_TOP = Path("", np.zeros(PATH_DIMS, np.float32))


def scanner(page: str) -> Callable[[int], tuple[int, int] | None]:
    """A function from a position to the (start, end) of the next comment, declaration or tag. A ``<`` that opens no tag is text. All
    calls together take linear time: what is known of a stretch that closes no tag is kept."""
    size = len(page)
    ends: dict[int, int] = {}  # from a special character outside quotes: where the tag ends, or -1
    near = (0, -1)  # from its first to its second position the next special character is the second
    missing = {c: size + 1 for c in ">\"'"}  # from here on the character doesn't occur

    def special(i: int) -> int:
        nonlocal near
        if not near[0] <= i <= near[1]:
            m = SPECIAL.search(page, i)
            near = (i, m.start() if m else size)
        return near[1]

    def find(c: str, i: int) -> int:
        if i >= missing[c]:
            return -1
        out = page.find(c, i)
        if out < 0:
            missing[c] = i
        return out

    def tag_end(i: int) -> int:
        way = []
        q = special(i)
        while True:
            out = ends.get(q)
            if out is None:
                if q >= size:
                    out = -1
                elif page[q] == ">":
                    out = q + 1
                else:
                    way.append(q)
                    close = find(page[q], q + 1)
                    if close >= 0:
                        q = special(close + 1)
                        continue
                    out = -1
            for w in way:
                ends[w] = out
            return out

    def token(at: int) -> tuple[int, int] | None:
        while True:
            i = page.find("<", at)
            if i < 0:
                return None
            c = page[i + 1 : i + 2]
            if page.startswith("<!--", i):
                end = page.find("-->", i + 4) + 3
                end = end if end > 2 else size
            elif page.startswith("<![CDATA[", i):
                end = page.find("]]>", i + 9) + 3
                end = end if end > 2 else size
            elif c in ("!", "?"):
                end = page.find(">", i + 2) + 1 or size
            else:
                d = page[i + 2 : i + 3] if c == "/" else c
                end = tag_end(i + 2 + (c == "/")) if d.isascii() and d.isalpha() else -1
            if end >= 0:
                return i, end
            at = i + 1

    return token


@lru_cache(100_000)
def _open(token: str) -> tuple[bool, str, tuple[str, ...]]:
    m = TAG.match(token)
    name = m[2].lower()
    marks = []
    if not m[1] and m[3]:
        for x in MARKS.finditer(m[3]):
            marks += WORDS.findall((x[1] or x[2] or x[3] or "").lower())
    return bool(m[1]), name, tuple(marks)


def blocks(page: str) -> list[Block]:
    """The non-empty leaf blocks of a page, in order."""
    if Path.made > MOST_PATHS:
        _TOP.below.clear()
        Path.made = 0
    out: list[Block] = []
    stack: list[Path] = []
    open_: Counter = Counter()
    pieces: list[str] = []
    linked, in_link, at = 0, 0, 0

    def flush() -> None:
        nonlocal linked
        if pieces:
            text = SPACE.sub(" ", entities.unescape("".join(pieces))).strip()
            pieces.clear()
            if text:
                out.append(Block(stack[-1] if stack else _TOP, text, linked))
        linked = 0

    following = scanner(page)
    while (found := following(at)) is not None:
        start, end = found
        if start > at:
            pieces.append(page[at:start])
            linked += (start - at) * bool(in_link)
        at, token = end, page[start:end]
        if token[1] in "!?":
            continue
        closing, name, marks = _open(token)
        if name in RAW:
            if not closing and not token.endswith("/>"):
                close = RAW_END[name].search(page, at)
                at = close.end() if close else len(page)
            continue
        if name not in BLOCK:
            if name == "a":
                in_link = 0 if closing else 1
            elif name == "br":
                pieces.append(" ")
            continue
        flush()
        if closing:
            if open_[name]:
                while True:
                    x = stack.pop().name
                    open_[x] -= 1
                    if x == name:
                        break
        elif name not in VOID:
            ends = SELF_CLOSING.get(name)
            if ends:
                while stack and stack[-1].name in ends:
                    open_[stack.pop().name] -= 1
            stack.append((stack[-1] if stack else _TOP).child(name, marks))
            open_[name] += 1
    if at < len(page):
        pieces.append(page[at:])
    flush()
    return out


@lru_cache(200_000)
def _slot(text: str, dims: int) -> tuple[int, float]:
    h = zlib.crc32(text.encode())
    return h % dims, 1.0 if h & 0x10000 else -1.0


def vectors(found: list[Block]) -> np.ndarray:
    x = np.zeros((len(found), DIMS), np.float32)
    n = len(found)
    words: list[tuple[int, float]] = []
    counts = np.zeros(n, np.int64)
    for k, b in enumerate(found):
        x[k, :PATH_DIMS] = b.path.vector
        own = [_slot(w, WORD_DIMS) for w in set(LETTERS.findall(b.text.lower()))]
        words += own
        counts[k] = len(own)
        size = len(b.text)
        x[k, -MEASURES:] = (np.log1p(size) / 5, min(1.0, b.linked / (size + 1)), k / n, float(b.text[-1] in ".!?"), min(1.0, b.text.count(",") * 20 / (size + 1)), 1.0)
    if words:
        slot, sign = (np.array(v) for v in zip(*words, strict=True))
        bag = np.bincount(np.repeat(np.arange(n), counts) * WORD_DIMS + slot, sign, n * WORD_DIMS).reshape(n, WORD_DIMS)
        x[:, PATH_DIMS : PATH_DIMS + WORD_DIMS] = np.clip(bag / np.sqrt(1 + counts)[:, None], -1, 1)
    return x


class Lstm:
    """A bidirectional LSTM with one output per step; all arrays in ``w``."""

    def __init__(self, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.w: dict[str, np.ndarray] = {}
        for d in "fb":
            self.w[d + "x"] = (rng.standard_normal((DIMS, 4 * HIDDEN)) / np.sqrt(DIMS)).astype(np.float32)
            self.w[d + "h"] = (rng.standard_normal((HIDDEN, 4 * HIDDEN)) / np.sqrt(HIDDEN)).astype(np.float32)
            self.w[d + "c"] = np.zeros(4 * HIDDEN, np.float32)
            self.w[d + "c"][HIDDEN : 2 * HIDDEN] = 1
        self.w["o"] = (rng.standard_normal(2 * HIDDEN) / np.sqrt(HIDDEN)).astype(np.float32)
        self.w["s"] = np.zeros(DIMS, np.float32)
        self.w["k"] = np.zeros(1, np.float32)

    def run(self, x: np.ndarray, d: str, keep: list | None = None) -> np.ndarray:
        """Hidden states for (steps, pages, DIMS), in reading order of direction ``d``."""
        steps, pages, _ = x.shape
        pre = x.reshape(-1, DIMS) @ self.w[d + "x"] + self.w[d + "c"]
        pre = pre.reshape(steps, pages, -1)
        h = c = np.zeros((pages, HIDDEN), np.float32)
        out = np.empty((steps, pages, HIDDEN), np.float32)
        for t in range(steps):
            z = pre[t] + h @ self.w[d + "h"]
            g = 1 / (1 + np.exp(-np.clip(z[:, : 3 * HIDDEN], -20, 20)))
            i, f, o = g[:, :HIDDEN], g[:, HIDDEN : 2 * HIDDEN], g[:, 2 * HIDDEN :]
            u = np.tanh(z[:, 3 * HIDDEN :])
            new = f * c + i * u
            tc = np.tanh(new)
            if keep is not None:
                keep.append((h, c, i, f, o, u, tc))
            h, c = o * tc, new
            out[t] = h
        return out

    def logits(self, x: np.ndarray, mask: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """(steps, pages); pages are padded at the end, so the backward direction reads each page flipped in place."""
        length = mask.sum(0).astype(np.int64)
        steps = np.arange(len(x))[:, None]
        flip = np.where(steps < length, length - 1 - steps, steps)
        xb = np.take_along_axis(x, flip[:, :, None], 0)
        kf, kb = ([], []) if keep is not None else (None, None)
        hf, hb = self.run(x, "f", kf), self.run(xb, "b", kb)
        hb = np.take_along_axis(hb, flip[:, :, None], 0)
        if keep is not None:
            keep.update(kf=kf, kb=kb, xb=xb, flip=flip, hf=hf, hb=hb)
        return hf @ self.w["o"][:HIDDEN] + hb @ self.w["o"][HIDDEN:] + x @ self.w["s"] + self.w["k"]

    def gradients(self, x: np.ndarray, mask: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        keep: dict = {}
        z = self.logits(x, mask, keep)
        p = 1 / (1 + np.exp(-np.clip(z, -20, 20)))
        n = mask.sum()
        loss = float(-(np.log(np.where(y > 0, p, 1 - p) + 1e-9) * mask).sum() / n)
        dz = ((p - y) * mask / n).astype(np.float32)
        g = {"o": np.concatenate([np.tensordot(dz, keep["hf"], 2), np.tensordot(dz, keep["hb"], 2)]), "s": np.tensordot(dz, x, 2), "k": np.array([dz.sum()])}
        for d, states, source in (("f", keep["kf"], x), ("b", keep["kb"], keep["xb"])):
            dh_out = dz[:, :, None] * (self.w["o"][:HIDDEN] if d == "f" else self.w["o"][HIDDEN:])
            if d == "b":
                dh_out = np.take_along_axis(dh_out, keep["flip"][:, :, None], 0)
            dpre = np.empty((*dz.shape, 4 * HIDDEN), np.float32)
            dh = dc = np.zeros((dz.shape[1], HIDDEN), np.float32)
            gh = np.zeros_like(self.w[d + "h"])
            for t in range(len(x) - 1, -1, -1):
                h, c, i, f, o, u, tc = states[t]
                dh = dh + dh_out[t]
                dc = dc + dh * o * (1 - tc * tc)
                dpre[t] = np.hstack([dc * u * i * (1 - i), dc * c * f * (1 - f), dh * tc * o * (1 - o), dc * i * (1 - u * u)])
                gh += h.T @ dpre[t]
                dh, dc = dpre[t] @ self.w[d + "h"].T, dc * f
            flat = dpre.reshape(-1, 4 * HIDDEN)
            g[d + "x"], g[d + "h"], g[d + "c"] = source.reshape(-1, DIMS).T @ flat, gh, flat.sum(0)
        return loss, g


def padded(pages: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    steps = max(map(len, pages))
    x, mask = np.zeros((steps, len(pages), DIMS), np.float32), np.zeros((steps, len(pages)), np.float32)
    for j, p in enumerate(pages):
        x[: len(p), j], mask[: len(p), j] = p, 1
    return x, mask


# fixed values: how pages name their parts
OUTSIDE = "nav menu navbar topnav breadcrumb breadcrumbs pagination header masthead banner footer foot copyright sidebar side rail widget related recommended trending ad ads advert advertisement sponsor sponsored promo notice cookie cookies consent gdpr alert modal popup overlay comment comments replies reply respond discussion disqus form search login signup subscribe newsletter share social tags meta author byline toolbar skip".split()
# words that parts outside the main text use, in four languages
PART_WORDS = {
    "consent": "cookie cookies consent accept privacy policy we use datenschutz zustimmen akzeptieren einwilligung accepter confidentialité aceptar privacidad",
    "rights": "copyright rights reserved terms imprint contact impressum alle rechte vorbehalten kontakt mentions légales tous droits réservés todos los derechos reservados aviso legal",
    "letter": "subscribe newsletter sign up email inbox weekly abonnieren anmelden abonnez vous inscrire suscríbete boletín correo",
    "reply": "comment comments reply replies posted by ago says kommentar kommentare antworten commentaire commentaires répondre comentario comentarios responder",
    "offer": "advertisement sponsored ad buy now offer sale discount shop anzeige werbung jetzt kaufen angebot publicité acheter offre publicidad comprar oferta",
    "more": "share tweet follow us related read more trending menu home login search teilen folgen mehr lesen partager suivez lire aussi compartir síguenos leer más",
}
# frequent words of running text in the same languages
PROSE_WORDS = "the of and to in that was it for on with as his they at from had this but not which she were der die und das den von zu mit sich auf für ist im dem nicht ein eine als auch es wurde war le la les des et en un une du dans qui que pour sur pas plus par au avec il elle était el los las del por una con no se su para como fue más pero".split()
INSIDE = "content main article post entry body story text articlebody maincontent postcontent entrycontent page".split()


def training_pages(n: int, seed: int = 11) -> list[tuple[str, list[int]]]:
    """(page, label of each block) from a grammar of page parts."""
    rng = np.random.default_rng(seed)
    pick = lambda xs: xs[int(rng.integers(len(xs)))]
    chance = lambda p: rng.random() < p

    parts_of = [x.split() for x in PART_WORDS.values()]

    def word(vocabulary: list[str] | None = None, share: float = 0.5) -> str:
        """Of a vocabulary with the chance ``share``, else letters at random."""
        if vocabulary and chance(share):
            return pick(vocabulary)
        return "".join(chr(97 + int(c)) for c in rng.integers(0, 26, int(rng.integers(2, 9))))

    def phrase(lo: int, hi: int, vocabulary: list[str] | None = None, share: float = 0.5) -> str:
        return " ".join(word(vocabulary, share) for _ in range(int(rng.integers(lo, hi + 1))))

    def sentences(hi: int = 60, vocabulary: list[str] | None = None, share: float = 0.5) -> str:
        return ". ".join(phrase(1, 25, vocabulary, share).capitalize() for _ in range(int(rng.integers(1, max(2, hi // 12))))) + pick([".", ".", ".", "", "!", ","])

    def prose(hi: int = 60) -> str:
        return sentences(hi, PROSE_WORDS, pick([0.0, 0.3, 0.5]))

    def notice() -> str:
        """Words of one part, a few sentences at most."""
        return sentences(30, pick(parts_of), pick([0.6, 0.8, 0.95]))

    def marks(names: list[str]) -> str:
        a = pick(names)
        return pick([f' class="{a}"', f' id="{a}"', f' class="{a} {phrase(1, 1)}"', f' class="{phrase(1, 1)}-{a}"', f' role="{a}"'])

    def part(label: int, depth: int = 0) -> tuple[str, list[int]]:
        """Some blocks of one label in their own tags."""
        k = int(rng.integers(1, 5))
        kind = rng.random()
        if kind < 0.25:
            return "<ul>" + "".join(f'<li><a href="/{phrase(1, 1)}">{phrase(1, 3)}</a></li>' if not label or chance(0.2) else f"<li>{prose()}</li>" for _ in range(k)) + "</ul>", [label] * k
        if kind < 0.4:
            level = 1 + int(rng.integers(4))
            return f"<h{level}>{phrase(1, 9)}</h{level}>", [label]
        if kind < 0.5:
            return f"<blockquote>{prose()}</blockquote>", [label]
        if kind < 0.56:
            return f"<table><tr><td>{phrase(1, 4)}</td><td>{phrase(1, 4)}</td></tr></table>", [label] * 2
        return "".join(f"<p>{'<b>' * chance(0.2)}{prose(120) if label or chance(0.5) else notice()}{'<br>' * chance(0.2)}{'</p>' * chance(0.8)}" for _ in range(k)), [label] * k

    def outside() -> tuple[str, list[int]]:
        tag = pick(["nav", "footer", "header", "aside", "form", "menu", "div", "div", "section", "ul", "nav", "footer"])
        named = marks(OUTSIDE) if tag in ("div", "section", "ul") or chance(0.3) else ""
        if tag in ("footer", "div", "section", "header", "aside") and chance(0.6):
            body, labels = pick([prose, sentences, notice])() if chance(0.7) else f"&copy; {phrase(1, 2)} &middot; {pick([sentences, notice])()}", [0]
        elif tag == "form":
            body, labels = f"<label>{phrase(1, 3)}</label><input><button>{phrase(1, 1)}</button>", [0]
        elif tag == "ul":
            body, labels = f"<li>{pick([sentences, notice])()}</li>", [0]
        else:
            parts = [part(0) for _ in range(int(rng.integers(1, 3)))]
            body, labels = "".join(p for p, _ in parts), sum((x for _, x in parts), [])
        return f"<{tag}{named}>{body}</{tag}>", labels

    def around() -> tuple[str, list[int]]:
        """A part outside the main text, or a notice in plain tags, which its words and its place tell from the text."""
        if chance(0.75):
            return outside()
        tag = pick(["p", "p", "div", "section"])
        return f"<{tag}>{notice()}</{tag}>", [0]

    def inside() -> tuple[str, list[int]]:
        parts = [(f"<h1>{phrase(1, 9)}</h1>", [1])] * chance(0.8) + [part(1) for _ in range(int(rng.integers(1, 7)))]
        if chance(0.3):
            parts.insert(int(rng.integers(len(parts) + 1)), outside())
        body, labels = "".join(p for p, _ in parts), sum((x for _, x in parts), [])
        kind = rng.random()
        if kind < 0.6:
            return f"<article{marks(INSIDE) if chance(0.2) else ''}>{body}</article>", labels
        if kind < 0.75:
            return f"<main>{body}</main>", labels
        tag = pick(["div", "section"])
        return f"<{tag}{marks(INSIDE)}>{body}</{tag}>", labels

    out = []
    for _ in range(n):
        parts = [around() for _ in range(int(rng.integers(0, 4)))] + [inside()] + [around() for _ in range(int(rng.integers(0, 4)))]
        if chance(0.2):
            inner, labels = "".join(p for p, _ in parts), sum((x for _, x in parts), [])
            parts = [(f"<div{marks(['wrapper', 'page', 'container', 'layout', 'site'])}>{inner}</div>", labels)]
        title = phrase(1, 9)
        page = f"<!DOCTYPE html><html><head><title>{title}</title></head><body>{''.join(p for p, _ in parts)}</body></html>"
        out.append((page, [0, *sum((x for _, x in parts), [])]))
    return out


@lru_cache(2)
def trained(pages: int = 600, epochs: int = 14, seed: int = 3) -> Lstm:
    """The labeller; always the same for the same arguments."""
    net = Lstm(seed)
    data = []
    for page, labels in training_pages(pages):
        found = blocks(page)
        if len(found) == len(labels) and found:
            data.append((vectors(found), np.array(labels, np.float32)))
    rng = np.random.default_rng(seed)
    m = {k: np.zeros_like(v) for k, v in net.w.items()}
    v = {k: np.zeros_like(x) for k, x in net.w.items()}
    step, size = 0, 25
    data.sort(key=lambda d: len(d[1]))
    groups = [data[i : i + size] for i in range(0, len(data), size)]
    for epoch in range(epochs):
        for j in rng.permutation(len(groups)):
            x, mask = padded([d[0] for d in groups[j]])
            y = np.zeros(mask.shape, np.float32)
            for i, d in enumerate(groups[j]):
                y[: len(d[1]), i] = d[1]
            _, g = net.gradients(x, mask, y)
            step += 1
            rate = 0.01 if epoch < epochs * 2 // 3 else 0.003
            for k, a in g.items():  # Adam
                a = np.clip(a, -1, 1)
                m[k] = 0.9 * m[k] + 0.1 * a
                v[k] = 0.99 * v[k] + 0.01 * a * a
                net.w[k] -= (rate * m[k] / (1 - 0.9**step) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-6)).astype(np.float32)
            for k in ("fx", "bx", "s"):  # words are many and mostly chance: what they don't earn decays
                net.w[k][PATH_DIMS : PATH_DIMS + WORD_DIMS] *= 1 - WORD_DECAY * rate
    return net


def label_pages(net: Lstm, pages: list[list[Block]], batch_steps: int = 4_000) -> list[np.ndarray]:
    """P(main text) of each block; pages of like length are read together."""
    out: list[np.ndarray] = [np.zeros(0)] * len(pages)
    order = sorted((i for i in range(len(pages)) if pages[i]), key=lambda i: len(pages[i]))
    lo = 0
    while lo < len(order):
        hi = lo + 1
        while hi < len(order) and (hi + 1 - lo) * len(pages[order[hi]]) <= batch_steps:
            hi += 1
        x, mask = padded([vectors(pages[i]) for i in order[lo:hi]])
        z = net.logits(x, mask)
        for j, i in enumerate(order[lo:hi]):
            out[i] = 1 / (1 + np.exp(-np.clip(z[: len(pages[i]), j], -20, 20)))
        lo = hi
    return out


def main_texts(net: Lstm, pages: list[str | None]) -> list[str]:
    found = [blocks(p or "") for p in pages]
    return ["\n".join(b.text for b, q in zip(bs, ps, strict=True) if q >= 0.5) for bs, ps in zip(found, label_pages(net, found), strict=True)]


def extract_pages(pages: DataFrame, net: Lstm | None = None) -> DataFrame:
    """(page_id, url, text, n_chars)"""
    shared = pages.sparkSession.sparkContext.broadcast(net or trained())

    def run(frames: Iterator[pd.DataFrame]):
        for pdf in frames:
            for lo in range(0, len(pdf), 200):
                some = pdf.iloc[lo : lo + 200]
                texts = main_texts(shared.value, some["html"].tolist())
                yield pd.DataFrame({"page_id": some["page_id"].to_numpy(), "url": some["url"].to_numpy(), "text": texts, "n_chars": [len(t) for t in texts]})

    return pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html").mapInPandas(run, "page_id long, url string, text string, n_chars long")
