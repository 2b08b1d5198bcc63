"""Word-level language identification by a linear-chain conditional random field.

Words carry byte n-grams (those at a boundary are affixes) and their own hash (the lexicon), all hashed into one
weight table. Transitions are learnt from sequences that join pieces of documents of several languages, as code-switched text
does. Forward-backward gives each word its marginals; a document's language is that of the largest mean.

All documents of a batch form one chain in which a reset stands between documents. The chain is cut into equal blocks:
block products are computed side by side, one scan joins them, and marginals follow side by side again. This is exact.

The weights are learnt on a sample of labelled documents bounded by ``sample`` rows and ``sample_chars`` characters
each row; every document is then labelled over its whole text. Defined results: null text or text without letters is
``und`` with score 0; repeated rows are alike; without training rows all is ``und``; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BASE, mix, slices, utf8, word_hashes, words

TABLE_BITS = 16
SAMPLE_ROWS, SAMPLE_CHARS = 2_000, 8_000
LETTER = np.zeros(256, np.uint8)
LETTER[97:123] = np.arange(97, 123)
LETTER[65:91] = np.arange(97, 123)
LETTER[128:] = np.arange(128, 256)


def features(raw: np.ndarray, offsets: np.ndarray):
    """(trigram, tetragram and position ranges, word hash, first): all words that have a letter."""
    c = LETTER[raw]
    starts, ends, _ = words(raw, offsets)
    has = np.add.reduceat((c > 0).astype(np.int32), starts) > 0 if len(starts) else np.zeros(0, bool)
    starts, ends = starts[has], ends[has]
    w = word_hashes(raw, starts, ends) >> np.uint64(64 - TABLE_BITS)
    p = np.zeros(len(c) + 3, np.uint32)
    p[1:-2] = c
    with np.errstate(over="ignore"):
        tri = p[:-3] * np.uint32(0x9E3779B1) ^ p[1:-2] * np.uint32(0x85EBCA6B) ^ p[2:-1] * np.uint32(0xC2B2AE35)
        tetra = (tri ^ p[3:] * np.uint32(0x27D4EB2F)) * np.uint32(0x165667B1) + np.uint32(0x51ED)
        tri = tri * np.uint32(0x2C1B3C6D)
    shift = np.uint32(32 - TABLE_BITS)
    return (tri >> shift).astype(np.int32), (tetra >> shift).astype(np.int32), starts, ends, w.astype(np.int32), np.searchsorted(starts, offsets)


def emissions(table: np.ndarray, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(scores of each word, first word of each row)"""
    tri, tetra, starts, ends, w, first = features(raw, offsets)
    k = table.shape[1]
    if not len(starts):
        return np.zeros((0, k)), first
    per = table[tri]
    per += table[tetra]
    sums = np.zeros((len(raw) + 1, k))
    np.cumsum(per, axis=0, out=sums[1:])
    size = (ends - starts)[:, None]
    return (sums[ends] - sums[starts]) / np.sqrt(size) + table[w], first


def marginals(scores: np.ndarray, reset: np.ndarray, trans: np.ndarray, prior: np.ndarray, pairs: bool = False):
    """P(label) of every word of a chain; ``reset`` marks the first word of each document. With ``pairs`` also the expected number of each transition."""
    n, k = scores.shape
    if not n:
        return (scores, np.zeros((k, k))) if pairs else scores
    length = max(1, int(np.sqrt(n)))
    blocks = -(-n // length)
    pad = blocks * length - n
    e = np.exp(scores - scores.max(1, keepdims=True))
    e = np.concatenate([e, np.ones((pad, k))]).reshape(blocks, length, k)
    r = np.concatenate([reset, np.ones(pad, bool)]).reshape(blocks, length)
    product = np.broadcast_to(np.eye(k), (blocks, k, k)).copy()
    for t in range(length):
        go = product @ trans
        at = r[:, t]
        if at.any():
            go[at] = product[at].sum(2, keepdims=True) * prior
        product = go * e[:, t, None, :]
        product /= product.sum((1, 2), keepdims=True)
    enter, leave = np.empty((blocks, k)), np.empty((blocks, k))
    a, b = np.full(k, 1 / k), np.ones(k)
    for j in range(blocks):
        enter[j] = a
        a = a @ product[j]
        a /= a.sum()
    for j in range(blocks - 1, -1, -1):
        leave[j] = b
        b = product[j] @ b
        b /= b.sum()
    alpha, a = np.empty((blocks, length, k)), enter
    for t in range(length):
        go = a @ trans
        at = r[:, t]
        if at.any():
            go[at] = prior
        a = go * e[:, t]
        a /= a.sum(1, keepdims=True)
        alpha[:, t] = a
    b = leave
    forward = alpha.copy() if pairs else None
    message = np.empty_like(alpha) if pairs else None
    for t in range(length - 1, -1, -1):
        alpha[:, t] *= b
        back = e[:, t] * b
        if pairs:
            message[:, t] = back
        b = back @ trans.T
        at = r[:, t]
        if at.any():
            b[at] = 1.0
        b /= b.sum(1, keepdims=True)
    out = alpha.reshape(-1, k)[:n]
    out = out / out.sum(1, keepdims=True)
    if not pairs:
        return out
    inside = np.flatnonzero(~reset)
    each = forward.reshape(-1, k)[inside - 1][:, :, None] * trans * message.reshape(-1, k)[inside][:, None, :]
    return out, (each / each.sum((1, 2), keepdims=True)).sum(0)


class Model:
    def __init__(self, labels: list[str], table: np.ndarray, trans: np.ndarray, prior: np.ndarray):
        self.labels, self.table, self.trans, self.prior = labels, table, trans, prior

    def word_marginals(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        scores, first = emissions(self.table, raw, offsets)
        reset = np.zeros(len(scores) + 1, bool)
        reset[first] = True
        return marginals(scores, reset[:-1], self.trans, self.prior), first

    def label_words(self, text: str) -> list[tuple[str, str]]:
        """(word, language) of each word of one text that has letters."""
        raw = np.frombuffer(text.encode(), np.uint8)
        p, _ = self.word_marginals(raw, np.array([0, len(raw)]))
        _, _, starts, ends, _, _ = features(raw, np.array([0, len(raw)]))
        return [(bytes(raw[s:e]).decode(), self.labels[i]) for s, e, i in zip(starts, ends, p.argmax(1), strict=True)]


def train(texts: list[str], langs: list[str], sequences: int = 3_000, length: int = 60, epochs: int = 3, seed: int = 7) -> Model:
    """Maximum likelihood by AdaGrad over joined pieces; gradients come from forward-backward."""
    labels = sorted(set(langs))
    k = len(labels)
    if not k:
        return Model([], np.zeros((1 << TABLE_BITS, 1), np.float32), np.ones((1, 1)), np.ones(1))
    rng = np.random.default_rng(seed)
    by = {x: [t.encode() for t, y in zip(texts, langs, strict=True) if y == x] for x in labels}
    pieces, gold = [], []
    for _ in range(sequences):
        n, left = 1 + int(rng.random() < 0.5) + int(rng.random() < 0.2), length
        parts, tags = [], []
        for j in range(n):
            x = int(rng.integers(k))
            ws = by[labels[x]][int(rng.integers(len(by[labels[x]])))].split()
            take = left if j == n - 1 else max(1, left // (n - j))
            at = int(rng.integers(max(1, len(ws) - take)))
            ws = [w for w in ws[at : at + take] if LETTER[np.frombuffer(w, np.uint8)].any()]
            parts += ws
            tags += [x] * len(ws)
            left -= take
        if parts:
            pieces.append(b" ".join(parts))
            gold.append(tags)
    table = np.zeros((1 << TABLE_BITS, k), np.float32)
    logt = np.zeros((k, k))
    sq, sqt = np.full(table.shape, 1e-2, np.float32), np.full((k, k), 1e-2)
    prior = np.full(k, 1 / k)
    step = 200
    for _ in range(epochs):
        for lo in range(0, len(pieces), step):
            batch = pieces[lo : lo + step]
            raw = np.frombuffer(b"".join(batch), np.uint8)
            offsets = np.cumsum([0, *map(len, batch)])
            y = np.concatenate([np.array(g) for g in gold[lo : lo + step]])
            trans = np.exp(logt - logt.max())
            tri, tetra, starts, ends, w, first = features(raw, offsets)
            scores, _ = emissions(table, raw, offsets)
            reset = np.zeros(len(scores) + 1, bool)
            reset[first] = True
            reset = reset[:-1]
            p, expected = marginals(scores, reset, trans, prior, pairs=True)
            diff = -p
            diff[np.arange(len(y)), y] += 1
            grad = np.zeros(table.shape)
            inner = np.repeat(diff / np.sqrt(ends - starts)[:, None], ends - starts, axis=0)
            at = np.concatenate([np.arange(s, e) for s, e in zip(starts, ends, strict=True)])
            for j in range(k):
                grad[:, j] = np.bincount(tri[at], inner[:, j], len(table)) + np.bincount(tetra[at], inner[:, j], len(table)) + np.bincount(w, diff[:, j], len(table))
            grad -= 1e-3 * table
            sq += (grad * grad).astype(np.float32)
            table += (0.3 * grad / np.sqrt(sq)).astype(np.float32)
            inside = np.flatnonzero(~reset)
            gt = -expected
            np.add.at(gt, (y[inside - 1], y[inside]), 1)
            sqt += gt * gt
            logt += 0.1 * gt / np.sqrt(sqt)
    trans = np.exp(logt - logt.max())
    return Model(labels, table, trans / trans.sum(1, keepdims=True), prior)


def training_rows(docs: DataFrame, sample: int = SAMPLE_ROWS, sample_chars: int = SAMPLE_CHARS, fold_left_out: int | None = 0) -> DataFrame:
    """(text, lang) of about ``sample`` documents for each language, chosen by a hash of the id."""
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.length("text") <= sample_chars) & (F.length("text") > 20))
    if fold_left_out is not None:
        rows = rows.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != fold_left_out)
    share = rows.groupBy("lang").agg((F.lit(1_000_000) * F.least(F.lit(1.0), F.lit(float(sample)) / F.count("*"))).alias("share"))
    return rows.join(F.broadcast(share), "lang").where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < F.col("share")).select("text", "lang")


def fit(docs: DataFrame, sample: int = SAMPLE_ROWS, fold_left_out: int | None = 0) -> Model:
    rows = training_rows(docs, sample, fold_left_out=fold_left_out).toPandas().sort_values(["lang", "text"], kind="stable")
    return train(rows["text"].tolist(), rows["lang"].tolist())


def _has_letter(text: str | None) -> bool:
    return bool(text) and any(c.isalpha() for c in text)


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, n_words, n_switches)"""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]):
        m = shared.value
        for whole in batches:
            for b in slices(whole):
                raw, offsets = utf8(b.column(1))
                if m.labels:
                    p, first = m.word_marginals(raw, offsets)
                    sums = np.zeros((len(p) + 1, len(m.labels)))
                    np.cumsum(p, axis=0, out=sums[1:])
                    count = np.diff(first)
                    mean = (sums[first[1:]] - sums[first[:-1]]) / np.maximum(count, 1)[:, None]
                    best = mean.argmax(1)
                    top = p.argmax(1)
                    change = np.zeros(len(p) + 1, np.int64)
                    change[1:-1] = np.cumsum(top[1:] != top[:-1]) if len(p) > 1 else 0
                    switches = [int(change[z - 1] - change[a]) if z > a else 0 for a, z in zip(first[:-1], first[1:], strict=True)]
                    pred = [m.labels[i] if n else "und" for i, n in zip(best, count, strict=True)]
                    score = np.where(count > 0, np.clip(mean.max(1), 0, 1), 0.0)
                    # bytes beyond ASCII count as letters above; where there are no others, ask Unicode
                    ascii_letters = np.zeros(len(raw) + 1, np.int64)
                    np.cumsum((LETTER[raw] > 0) & (raw < 128), out=ascii_letters[1:])
                    doubt = np.flatnonzero((ascii_letters[offsets[1:]] == ascii_letters[offsets[:-1]]) & (count > 0))
                    for i in doubt:
                        if not _has_letter(b.column(1)[int(i)].as_py()):
                            pred[i], score[i] = "und", 0.0
                else:
                    pred, score, count, switches = ["und"] * b.num_rows, np.zeros(b.num_rows), np.zeros(b.num_rows, np.int64), [0] * b.num_rows
                yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(pred, pa.string()), pa.array(score, pa.float64()), pa.array(count.astype(np.int64)), pa.array(switches, pa.int64())], ["doc_id", "lang_pred", "score", "n_words", "n_switches"])

    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, lang_pred string, score double, n_words long, n_switches long")
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    return out.select("doc_id", held.alias("held_out"), "lang_pred", "score", "n_words", "n_switches")
