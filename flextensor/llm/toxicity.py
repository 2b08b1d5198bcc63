"""Toxicity by a weighted lexicon.

Texts are folded (case, homoglyphs of other scripts, digits and signs that stand for letters, invisible characters), all that isn't a
letter becomes one space, and an Aho-Corasick automaton finds the lexicon's words and word beginnings together with
exception phrases, whose inner matches don't count. The weights found, alone and per word of the text, give the score
through a logistic curve.

The lexicon, its weights, the exceptions and the curve are learnt from a sample of labelled documents of which ``sample``
bounds the size; every other step reads all of every text.

Defined results: null and empty texts get the score of a text without matches; repeated rows are scored alike; an
empty label table gives the built-in lexicon's score; an empty table an empty result; further columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SAMPLE_ROWS = 12_000
THRESHOLD = 0.3
# fixed values: Cyrillic and Greek letters that look like Latin ones, in the order of LOOKS_LIKE
HOMOGLYPHS = "аеорсухікмтвнԁѕјαορικτυνε"
LOOKS_LIKE = "aeopcyxikmtbhdsjaopiktuve"
DIGITS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s"}
# fixed values: words that insult in any text, used where there are no labels to learn from
DEFAULT_LEXICON = {w: 4.0 for w in ("idiot", "moron", "stupid", "scum", "trash", "loser", "worthless", "pathetic", "disgusting", "clown")}

_INVISIBLE = dict.fromkeys([0xAD, 0x200B, 0x200C, 0x200D, 0x2060, 0xFEFF])
_WIDE = {0xFF01 + i: chr(0x21 + i).lower() for i in range(94)}
FOLDING = {**{ord(a): b for a, b in zip(HOMOGLYPHS, LOOKS_LIKE, strict=True)}, **_WIDE, **_INVISIBLE}
LEET = {ord(a): b for a, b in DIGITS.items()}
GAP = re.compile(r"[\W_]+")
WORD = re.compile(r"[^\W\d_]\w*")
RUN = re.compile(r"[\w@$]+")
LETTER, SIGN = re.compile(r"[^\W\d_]"), re.compile(r"[0134578@$]")


def fold(text: str) -> str:
    """Folded text: words apart by one space, a space at each end. Signs count as letters only inside words that have letters."""
    t = text.lower()
    if not t.isascii():
        t = t.translate(FOLDING)
    if SIGN.search(t):
        t = RUN.sub(lambda m: m[0].rstrip("@$").translate(LEET) if SIGN.search(m[0]) and LETTER.search(m[0]) else m[0], t)
    return f" {GAP.sub(' ', t).strip()} "


class Lexicon:
    """Weights of words (`` word ``) and beginnings (`` word``), exception phrases, and the curve of the score."""

    def __init__(self, weights: dict[str, float], exceptions: list[str] = (), curve: tuple[float, float, float] = (-3.0, 1.5, 0.5)):
        self.weights, self.exceptions, self.curve = weights, list(exceptions), curve
        self._automaton = None

    def __getstate__(self):
        return {"weights": self.weights, "exceptions": self.exceptions, "curve": self.curve, "_automaton": None}

    def automaton(self):
        if self._automaton is None:
            import ahocorasick

            a = ahocorasick.Automaton()
            for p, w in self.weights.items():
                a.add_word(p, (p, w))
            for p in self.exceptions:
                a.add_word(f" {p.strip()} ", (f" {p.strip()} ", None))
            a.make_automaton()
            self._automaton = a
        return self._automaton

    def match(self, folded: str) -> float:
        """The sum of weights of matches outside exception phrases; of several patterns at one word the heaviest counts."""
        a = self.automaton()
        if not len(a):
            return 0.0
        best: dict[int, float] = {}
        spared: list[tuple[int, int]] = []
        for end, (p, w) in a.iter(folded):
            start = end - len(p) + 1
            if w is None:
                spared.append((start, end))
            else:
                best[start] = max(w, best.get(start, -math.inf))
        if not spared:
            return sum(best.values())
        spared.sort()
        total, at, until = 0.0, 0, -1  # matches and exceptions are met in the order of the text
        for s, w in sorted(best.items()):
            while at < len(spared) and spared[at][0] <= s:
                until = max(until, spared[at][1])
                at += 1
            if s >= until:
                total += w
        return total

    def features(self, text: str | None) -> tuple[float, float]:
        folded = fold(text or "")
        total = max(0.0, self.match(folded))
        return math.log1p(total), total / math.sqrt(folded.count(" ") + 20)

    def score(self, text: str | None) -> float:
        x, y = self.features(text)
        b, u, v = self.curve
        z = min(30.0, max(-30.0, b + u * x + v * y))
        return 1 / (1 + math.exp(-z))


def _presence(folded: list[str], labels: np.ndarray, terms_of, least: int) -> tuple[Counter, Counter]:
    """Toxic and other texts with each term that occurs in ``least`` toxic ones."""
    hit: Counter = Counter()
    for t in (t for t, y in zip(folded, labels, strict=True) if y):
        hit.update(terms_of(t.split()))
    hit = Counter({w: h for w, h in hit.items() if h >= least})
    miss: Counter = Counter()
    for t in (t for t, y in zip(folded, labels, strict=True) if not y):
        miss.update(w for w in terms_of(t.split()) if w in hit)
    return hit, miss


def learn(texts: list[str], labels: list[int], support: int = 8, odds: float = 2.5) -> Lexicon:
    """A lexicon from labelled texts."""
    y = np.asarray(labels, bool)
    if not y.any() or y.all():
        return Lexicon({f" {w} ": v for w, v in DEFAULT_LEXICON.items()})
    folded = [fold(t or "") for t in texts]
    n1, n0 = int(y.sum()), int((~y).sum())

    def strength(h: int, m: int) -> float:
        return math.log((h + 0.5) / (n1 + 1)) - math.log((m + 0.5) / (n0 + 1))

    weights: dict[str, float] = {}
    hit, miss = _presence(folded, y, set, 2 * support)
    whole = {w for w, h in hit.items() if strength(h, miss[w]) >= odds + 1.5 and len(w) >= 3}
    weights |= {f" {w} ": strength(hit[w], miss[w]) for w in whole}
    # word beginnings explain what whole words, each too rare, can't
    starts = lambda ws: {w[:k] for w in set(ws) - whole for k in range(4, 10) if len(w) >= k}
    hit, miss = _presence(folded, y, starts, support)
    good = sorted((p for p, h in hit.items() if strength(h, miss[p]) >= odds), key=lambda p: (len(p), p))
    kept: dict[str, float] = {}
    for p in good:
        s = strength(hit[p], miss[p])
        if all(s > kept.get(p[:k], -9.0) + 1.0 for k in range(4, len(p))):
            kept[p] = s
    weights |= {f" {p}": s for p, s in kept.items()}
    # phrases in which a word of the lexicon is harmless
    spoken = lambda ws: {f"{a} {b}" for a, b in zip(ws, ws[1:], strict=False) if a in whole or b in whole}
    miss, hit = _presence(folded, ~y, spoken, support)
    exceptions = [p for p, m in miss.items() if strength(hit[p], m) < 0]
    lex = Lexicon(weights, exceptions)
    x = np.array([(1.0, *lex.features(t)) for t in texts])
    w = np.array([-3.0, 1.0, 0.1])
    for _ in range(30):  # Newton steps of a ridge logistic regression
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + 0.1 * w
        h = (x * (p * (1 - p) + 1e-6)[:, None]).T @ x + 0.1 * np.eye(3)
        w = w - np.linalg.solve(h, g)
    lex.curve = tuple(float(v) for v in w)
    return lex


def training_rows(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE_ROWS, fold_left_out: int | None = 2) -> DataFrame:
    """(text, toxic) of about ``sample`` labelled documents, chosen by a hash of the id."""
    known = labels.where("toxic is not null and doc_id is not null").select("doc_id", "toxic")
    if fold_left_out is not None:
        known = known.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 != fold_left_out)
    share = min(1.0, sample / max(1, known.count()))
    known = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(share * 1_000_000)).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    return docs.select("doc_id", "text").join(F.broadcast(known), "doc_id").select("text", "toxic")


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE_ROWS, fold_left_out: int | None = 2) -> Lexicon:
    rows = training_rows(docs, labels, sample, fold_left_out).toPandas()
    rows = rows.sort_values(["toxic", "text"], kind="stable")
    return learn(rows["text"].tolist(), rows["toxic"].tolist())


def score_documents(docs: DataFrame, lexicon: Lexicon, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, held_out, score, predicted)"""
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    def run(frames: Iterator[pd.DataFrame]):
        for pdf in frames:
            s = [shared.value.score(t) for t in pdf["text"]]
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "score": s})

    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInPandas(run, "doc_id long, score double")
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, lexicon: Lexicon, threshold: float = THRESHOLD) -> DataFrame:
    """The documents whose score is under the threshold, with all their columns, in one pass without a join."""
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    @F.pandas_udf("double")
    def score(text: pd.Series) -> pd.Series:
        return pd.Series([shared.value.score(t) for t in text], dtype="float64")

    return docs.where(score("text") < threshold)
