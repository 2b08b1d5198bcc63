"""What several operators share: UTF-8 buffers of Arrow columns, word and shingle hashes, batch slicing."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE_BYTES = 1 << 20

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32

BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
BASE_INV = np.uint64(pow(int(BASE), -1, 1 << 64))
_POWERS: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE ** i and its inverse modulo 2 ** 64, i < n."""
    if len(_POWERS.get("up", ())) < n:
        m = max(n, SLICE_BYTES + 1)
        with np.errstate(over="ignore"):
            for name, b in (("up", BASE), ("down", BASE_INV)):
                p = np.full(m, b, np.uint64)
                p[0] = 1
                _POWERS[name] = np.cumprod(p, dtype=np.uint64)
    return _POWERS["up"][:n], _POWERS["down"][:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> np.uint64(30))
        x = x * np.uint64(0xBF58476D1CE4E5B9)
        x = x ^ (x >> np.uint64(27))
        x = x * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def slices(batch: pa.RecordBatch, text: str = "text") -> Iterator[pa.RecordBatch]:
    """The batch in runs of about SLICE_BYTES of text, one row at least."""
    n = batch.num_rows
    if not n:
        return
    col = batch.column(batch.schema.get_field_index(text))
    lengths = pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False)
    start, size = 0, 0
    for i, k in enumerate(lengths):
        if i > start and size + k > SLICE_BYTES:
            yield batch.slice(start, i - start)
            start, size = i, 0
        size += int(k)
    yield batch.slice(start)


def utf8(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; nulls are empty."""
    if pa.types.is_large_string(col.type):
        kind = np.int64
    else:
        col, kind = col.cast(pa.string()), np.int32
    if col.null_count:
        col = pc.fill_null(col, "")
    _, off, data = col.buffers()
    offsets = np.frombuffer(off, kind, len(col) + 1, col.offset * np.dtype(kind).itemsize).astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def words(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, first): words are runs of bytes that aren't white space; words first[d]:first[d+1] are row d's."""
    n = len(raw)
    inside = np.zeros(n + 1, bool)
    inside[:n] = ~SPACE[raw]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    before = np.zeros(n + 1, bool)
    before[1:] = inside[:n]
    starts = np.flatnonzero(inside & (edge | ~before))
    ends = np.flatnonzero(before & (edge | ~inside))
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    up, down = powers(len(raw) + 1)
    with np.errstate(over="ignore"):
        sums = np.zeros(len(raw) + 1, np.uint64)
        np.cumsum((FOLD[raw].astype(np.uint64) + np.uint64(1)) * up[:-1], out=sums[1:])
        return mix((sums[ends] - sums[starts]) * down[starts])


def shingle_sets(raw: np.ndarray, offsets: np.ndarray, k: int = 5) -> list[np.ndarray]:
    """For each row the sorted distinct hashes of its k-word shingles; fewer words make one shingle, none no shingle."""
    starts, ends, first = words(raw, offsets)
    w = word_hashes(raw, starts, ends)
    with np.errstate(over="ignore"):
        rolled = np.zeros(max(0, len(w) - k + 1), np.uint64)
        for j in range(k):
            rolled = rolled * BASE + w[j : j + len(rolled)]
        rolled = mix(rolled)
        out = []
        for a, b in zip(first[:-1], first[1:], strict=True):
            if b - a >= k:
                out.append(np.unique(rolled[a : b - k + 1]))
            elif b > a:
                h = np.uint64(b - a)
                for x in w[a:b]:
                    h = h * BASE + x
                out.append(mix(np.array([h], np.uint64)))
            else:
                out.append(np.zeros(0, np.uint64))
    return out
