"""PII by information-theoretic sanitisation.

Four kinds of entities are found by their form (e-mail, IP address, card, phone). Terms may reveal them as well: over
the sentences of the whole corpus, co-occurrence of a term with the protected kinds gives its disclosure, the pointwise
mutual information of term and kind over the information of the kind. The share of a term's sentences that hold the kind
is smoothed by ``PRIOR`` sentences with the kind's own share, so that disclosure nears 1 as a term that never occurs
without the kind is seen more often. Terms over ``generalise`` become, wherever they occur, spans to be replaced by a
class, those over ``remove`` spans to be dropped.

Counts cover all documents: one pass counts, exactly, terms in sentences with an entity; a second pass counts, in all
texts, the sentences of these terms, found through a Bloom filter of bounded size and made exact by a join.

Defined results: null texts are empty; repeated rows count and are searched each on their own; an empty table gives an
empty result; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import cut_lineage

KINDS = ("email", "ip", "card", "phone")
# fixed patterns: the forms of the four kinds
DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
TERM = re.compile(r"[^\W\d_]{3,}")
SENTENCE = re.compile(r"\n+|(?<=[.!?])\s+")
PRIOR = 1
BLOOM_BITS = 1 << 24


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) by kind, then start. Time is linear in the text."""
    out = []
    end = 0
    if "@" in text:
        for m in DOMAIN.finditer(text):
            s = m.start()
            while s > end and text[s - 1] in LOCAL:
                s -= 1
            if s < m.start():
                end = m.end()
                out.append(("email", s, end))
    if not re.search("[0-9]", text):
        return out
    for m in IP.finditer(text):
        if all(len(p := x.lstrip("0")) <= 3 and int(p or 0) <= 255 for x in m[0].split(".")):
            out.append(("ip", m.start(), m.end()))
    for m in CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 16 <= len(digits) <= 19 and luhn(digits):
            out.append(("card", m.start(), m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 8 <= sum("0" <= c <= "9" for c in m[0]) <= 15:
                out.append(("phone", m.start(), m.end()))
    return out


def sentences(text: str) -> Iterator[tuple[int, int]]:
    """(start, end) of each sentence or line."""
    at = 0
    for m in SENTENCE.finditer(text):
        yield at, m.start()
        at = m.end()
    yield at, len(text)


def terms_of(text: str, start: int, end: int) -> set[str]:
    return {t.lower() for t in TERM.findall(text, start, end)}


def _near_counts(docs: DataFrame) -> DataFrame:
    """(term, kind, n): sentences with the term in which an entity of the kind starts; the empty term counts them all."""

    def run(frames: Iterator[pd.DataFrame]):
        for pdf in frames:
            seen: Counter = Counter()
            for text in pdf["text"]:
                base = sorted((s, e, k) for k, s, e in base_spans(text)) if text else []
                if not base:
                    continue
                at = 0
                for a, b in sentences(text):
                    kinds, cut = set(), []
                    while at < len(base) and base[at][0] < b:
                        kinds.add(base[at][2])
                        cut.append(base[at][:2])
                        at += 1
                    if kinds:
                        inner = terms_outside(text, a, b, cut)
                        for kind in kinds:
                            seen["", kind] += 1
                            for t in inner:
                                seen[t, kind] += 1
                    if at == len(base):
                        break
            yield pd.DataFrame([(t, k, n) for (t, k), n in seen.items()], columns=["term", "kind", "n"])

    return docs.mapInPandas(run, "term string, kind string, n long").groupBy("term", "kind").agg(F.sum("n").alias("n"))


def terms_outside(text: str, start: int, end: int, spans: list[tuple[int, int]]) -> set[str]:
    """Terms of a sentence without those inside its entities."""
    out: set[str] = set()
    for s, e in spans:
        if s > start:
            out |= terms_of(text, start, s)
        start = max(start, e)
    return out | terms_of(text, start, end) if start < end else out


def _bits(terms) -> np.ndarray:
    import zlib

    return np.array([[zlib.crc32(b) % BLOOM_BITS, zlib.adler32(b, 77) * 2654435761 % BLOOM_BITS] for b in (t.encode() for t in terms)], np.int64).reshape(-1, 2)


def _term_counts(docs: DataFrame, bloom) -> DataFrame:
    """(term, n): sentences of all texts with the term, for terms that pass the Bloom filter; the empty term counts all sentences."""

    def run(frames: Iterator[pd.DataFrame]):
        table, known = bloom.value, {}
        for pdf in frames:
            seen: Counter = Counter()
            total = 0
            for text in pdf["text"]:
                if text:
                    for a, b in sentences(text):
                        total += 1
                        seen.update(terms_of(text, a, b))
            folded: Counter = Counter()
            for low, n in seen.items():
                hit = known.get(low)
                if hit is None:
                    if len(known) > 200_000:
                        known.clear()
                    hit = known[low] = bool(table[_bits([low])].all())
                if hit:
                    folded[low] += n
            folded[""] = total
            yield pd.DataFrame(list(folded.items()), columns=["term", "n"])

    return docs.mapInPandas(run, "term string, n long").groupBy("term").agg(F.sum("n").alias("n"))


def _bloom(terms: DataFrame) -> np.ndarray:
    table = np.zeros(BLOOM_BITS, bool)
    batch: list[str] = []
    for r in terms.select("term").distinct().toLocalIterator():
        batch.append(r.term)
        if len(batch) == 10_000:
            table[_bits(batch)] = True
            batch = []
    table[_bits(batch)] = True
    return table


def disclosing_terms(docs: DataFrame, generalise: float = 0.5) -> DataFrame:
    """(term, disclosure) of at least ``generalise`` for some kind, from counts over all of ``docs`` (text)."""
    near = cut_lineage(_near_counts(docs))
    counts = cut_lineage(_term_counts(docs, docs.sparkSession.sparkContext.broadcast(_bloom(near.where("term <> ''")))))
    total = counts.where("term = ''").agg(F.sum("n")).first()[0] or 1
    kinds = near.where("term = ''").select("kind", F.col("n").alias("n_kind"))
    joined = near.where("term <> ''").join(counts.withColumnRenamed("n", "n_term"), "term").join(F.broadcast(kinds), "kind")
    p_kind = F.col("n_kind") / float(total)
    share = (F.col("n") + PRIOR * p_kind) / (F.col("n_term") + PRIOR)
    found = joined.where("n_kind < %d" % total).select("term", F.least(F.lit(1.0), F.log(share / p_kind) / -F.log(p_kind)).alias("disclosure"))
    return found.where(F.col("disclosure") >= generalise).groupBy("term").agg(F.max("disclosure").alias("disclosure"))


class Sanitiser:
    """Applies disclosing terms to texts."""

    def __init__(self, terms: dict[str, float], remove: float = 0.9):
        self.terms, self.remove = terms, remove

    def spans(self, text: str) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
        """(base spans, spans of revealing terms: ``term`` to generalise, ``term_x`` to remove)"""
        base = base_spans(text)
        extra = {}
        if self.terms:
            taken = sorted((s, e) for _, s, e in base)
            at = 0
            for m in TERM.finditer(text):
                d = self.terms.get(m[0].lower())
                if d is None:
                    continue
                while at < len(taken) and taken[at][1] <= m.start():
                    at += 1
                if not any(s < m.end() and m.start() < e for s, e in taken[at : at + len(KINDS)]):
                    extra[m.span()] = d
        found = [("term_x" if d >= self.remove else "term", a, b) for (a, b), d in extra.items()]
        return base, sorted(found)

    def clean(self, text: str) -> str:
        base, extra = self.spans(text)
        out, at = [], 0
        for s, e, kind in sorted((s, e, k) for k, s, e in (*base, *extra)):
            if s >= at:
                out += [text[at:s], "" if kind == "term_x" else f"[{kind.upper()}]"]
                at = e
        return "".join(out) + text[at:]


def _fit(docs: DataFrame, generalise: float, most: int):
    """(disclosing terms, whether there are few enough to broadcast)"""
    terms = cut_lineage(disclosing_terms(docs, generalise=generalise))
    return terms, terms.count() <= most


def _apply(docs: DataFrame, terms: DataFrame, small: bool, remove: float, row, schema: str) -> DataFrame:
    if small:
        known = docs.sparkSession.sparkContext.broadcast({r.term: r.disclosure for r in terms.toLocalIterator()})

        def run(frames):
            tool = Sanitiser(known.value, remove)
            for pdf in frames:
                yield pd.DataFrame([row(tool, d, t or "") for d, t in zip(pdf["doc_id"], pdf["text"], strict=True)], columns=[c.split()[0] for c in schema.split(", ")])

        return docs.mapInPandas(run, schema)

    # too many terms for a broadcast: each text, known by its hash, meets its own terms through a join
    bloom = docs.sparkSession.sparkContext.broadcast(_bloom(terms))
    docs = docs.withColumn("text_key", F.xxhash64(F.coalesce("text", F.lit(""))))

    def emit(frames):
        for pdf in frames:
            rows: list = []
            for key, text in zip(pdf["text_key"], pdf["text"], strict=True):
                own = list(terms_of(text, 0, len(text))) if text else []
                if own:
                    rows += [(key, t) for t, hit in zip(own, bloom.value[_bits(own)].all(axis=1), strict=True) if hit]
            yield pd.DataFrame(rows, columns=["text_key", "term"])

    own = docs.select("text_key", "text").mapInPandas(emit, "text_key long, term string").distinct().join(terms, "term").groupBy("text_key").agg(F.collect_list(F.struct("term", "disclosure")).alias("terms"))

    def run_joined(frames):
        for pdf in frames:
            tools = [Sanitiser({r["term"]: r["disclosure"] for r in x} if x is not None else {}, remove) for x in pdf["terms"]]
            yield pd.DataFrame([row(s, d, t or "") for s, d, t in zip(tools, pdf["doc_id"], pdf["text"], strict=True)], columns=[c.split()[0] for c in schema.split(", ")])

    return docs.join(own, "text_key", "left").drop("text_key").mapInPandas(run_joined, schema)


def find_personal_data(docs: DataFrame, generalise: float = 0.5, remove: float = 0.9, most_broadcast: int = 500_000) -> DataFrame:
    """Per document the counts, digest and list of spans of personal data."""

    def row(tool: Sanitiser, doc, text: str):
        base, extra = tool.spans(text)
        text_of = lambda spans: ",".join(f"{k}:{s}:{e}" for k, s, e in spans)
        n = Counter(k for k, _, _ in base)
        b = text_of(base)
        return (doc, *(n[k] for k in KINDS), hashlib.sha256(b.encode()).hexdigest(), text_of([*base, *extra]))

    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    terms, small = _fit(docs.select("text"), generalise, most_broadcast)
    return _apply(docs, terms, small, remove, row, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string")


def sanitise_documents(docs: DataFrame, generalise: float = 0.5, remove: float = 0.9, most_broadcast: int = 500_000) -> DataFrame:
    """(doc_id, text) with entities and revealing terms generalised to a class or removed."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    terms, small = _fit(docs.select("text"), generalise, most_broadcast)
    return _apply(docs, terms, small, remove, lambda tool, doc, text: (doc, tool.clean(text)), "doc_id long, text string")
