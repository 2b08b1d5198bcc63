"""Telephony audio columns: mu-law, A-law and IMA ADPCM in WAV containers.

Companded bytes are expanded to 16-bit PCM by 256-entry lookup tables built from the codecs' rules; ADPCM blocks are
decoded step by step, all blocks of many files at once; PCM is resampled by a windowed-sinc filter. Any byte is a valid
companded sample and any nibble a valid ADPCM code, so ``store_payload`` keeps bytes losslessly in each codec; documents
are dealt over the three by their content.

Defined results: null media gives null columns, null text the empty payload; a container that can't be read raises
ValueError in ``decode_wav`` and gives null PCM in ``decode_media``; repeated rows are independent; empty tables give
empty results; further columns stay out of the result of the digest query.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

PCM, ALAW, MULAW, IMA = 1, 6, 7, 17
# fixed values: step sizes and index changes of the IMA ADPCM codec
STEPS = np.array(
    [7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767],
    np.int32,
)
INDEX = np.array([-1, -1, -1, -1, 2, 4, 6, 8] * 2, np.int32)


def mulaw_table() -> np.ndarray:
    code = ~np.arange(256, dtype=np.int32) & 0xFF
    size = (((code & 15) << 3) + 0x84 << (code >> 4 & 7)) - 0x84
    return np.where(code & 0x80, -size, size).astype(np.int16)


def alaw_table() -> np.ndarray:
    code = np.arange(256, dtype=np.int32) ^ 0x55
    exponent, mantissa = code >> 4 & 7, (code & 15) << 4
    size = np.where(exponent == 0, mantissa + 8, mantissa + 0x108 << np.maximum(exponent - 1, 0))
    return np.where(code & 0x80, size, -size).astype(np.int16)


TABLES = {MULAW: mulaw_table(), ALAW: alaw_table()}


def compress(pcm: np.ndarray, codec: int) -> np.ndarray:
    """Nearest code of each sample."""
    table = TABLES[codec].astype(np.int32)
    order = np.argsort(table, kind="stable")
    levels = table[order]
    x = pcm.astype(np.int32)
    i = np.clip(np.searchsorted(levels, x), 1, 255)
    return order[np.where(x - levels[i - 1] <= levels[i] - x, i - 1, i)].astype(np.uint8)


def ima_decode(data: bytes, block: int, samples: int) -> np.ndarray:
    """Mono IMA ADPCM: every step decodes one nibble of all blocks."""
    n = len(data) // block
    raw = np.frombuffer(data, np.uint8, n * block).reshape(n, block)
    value = raw[:, :2].copy().view("<i2")[:, 0].astype(np.int32)
    index = np.clip(raw[:, 2].astype(np.int32), 0, 88)
    nibbles = np.stack([raw[:, 4:] & 15, raw[:, 4:] >> 4], 2).reshape(n, -1)
    out = np.empty((n, nibbles.shape[1] + 1), np.int16)
    out[:, 0] = value
    for j in range(nibbles.shape[1]):
        q, step = nibbles[:, j].astype(np.int32), STEPS[index]
        change = (step >> 3) + np.where(q & 4, step, 0) + np.where(q & 2, step >> 1, 0) + np.where(q & 1, step >> 2, 0)
        value = np.clip(value + np.where(q & 8, -change, change), -32768, 32767)
        index = np.clip(index + INDEX[q], 0, 88)
        out[:, j + 1] = value
    return out.reshape(-1)[:samples]


def ima_encode(pcm: np.ndarray, block: int = 256) -> bytes:
    per = (block - 4) * 2 + 1
    n = -(-len(pcm) // per)
    x = np.zeros(n * per, np.int32)
    x[: len(pcm)] = pcm
    x = x.reshape(n, per)
    value, index = x[:, 0].copy(), np.zeros(n, np.int32)
    codes = np.zeros((n, per - 1), np.uint8)
    for j in range(1, per):
        step, gap = STEPS[index], x[:, j] - value
        q, left, change = np.where(gap < 0, 8, 0), np.abs(gap), step >> 3
        for bit, part in ((4, step), (2, step >> 1), (1, step >> 2)):
            on = left >= part
            q, left, change = q | np.where(on, bit, 0), left - np.where(on, part, 0), change + np.where(on, part, 0)
        value = np.clip(value + np.where(q & 8, -change, change), -32768, 32767)
        index = np.clip(index + INDEX[q], 0, 88)
        codes[:, j - 1] = q
    head = np.zeros((n, 4), np.uint8)
    head[:, :2] = x[:, 0].astype("<i2").view(np.uint8).reshape(n, 2)
    return np.hstack([head, codes[:, ::2] | codes[:, 1::2] << 4]).tobytes()


def wav(codec: int, data: bytes, samples: int, rate: int = 8000, block: int = 1) -> bytes:
    bits = {PCM: 16, IMA: 4}.get(codec, 8)
    block = 2 if codec == PCM else block
    extra = struct.pack("<HH", 2, (block - 4) * 2 + 1) if codec == IMA else struct.pack("<H", 0)
    speed = rate * 2 if codec == PCM else rate if codec != IMA else rate * block // ((block - 4) * 2 + 1)
    fmt = struct.pack("<HHIIHH", codec, 1, rate, speed, block, bits) + extra
    body = b"".join(name + struct.pack("<I", len(x)) + x + b"\0" * (len(x) % 2) for name, x in ((b"fmt ", fmt), (b"fact", struct.pack("<I", samples)), (b"data", data)))
    return b"RIFF" + struct.pack("<I", len(body) + 4) + b"WAVE" + body


def read_wav(media: bytes) -> tuple[int, int, int, int, bytes]:
    """(codec, rate, block, samples, data)"""
    if len(media) < 12 or media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a RIFF WAVE file")
    at, fmt, samples = 12, None, -1
    while at + 8 <= len(media):
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"fmt ":
            fmt = struct.unpack_from("<HHIIHH", media, at + 8)
        elif name == b"fact":
            samples = struct.unpack_from("<I", media, at + 8)[0]
        elif name == b"data":
            if fmt is None or fmt[1] != 1 or fmt[0] not in (PCM, ALAW, MULAW, IMA):
                raise ValueError("unknown format")
            data = media[at + 8 : at + 8 + size]
            if samples < 0:
                samples = len(data) // max(1, fmt[4]) * ((fmt[4] - 4) * 2 + 1) if fmt[0] == IMA else len(data) // max(1, fmt[4])
            return fmt[0], fmt[2], fmt[4], samples, data
        at += 8 + size + size % 2
    raise ValueError("no data chunk")


def decode_wav(media: bytes) -> tuple[int, np.ndarray]:
    """(rate, 16-bit PCM)"""
    codec, rate, block, samples, data = read_wav(media)
    if codec == IMA:
        return rate, ima_decode(data, block, samples)
    if codec == PCM:
        return rate, np.frombuffer(data, "<i2", samples)
    return rate, TABLES[codec][np.frombuffer(data, np.uint8, samples)]


def _kernel(up: int, down: int, half: int = 8) -> np.ndarray:
    """Low-pass of 2 * half * max(up, down) + 1 taps, split by the phases of ``up``."""
    m = max(up, down)
    t = np.arange(-half * m, half * m + 1)
    taps = np.sinc(t / m) * np.hanning(len(t) + 2)[1:-1] / m * up
    return taps


def resample(pcm: np.ndarray, rate: int, target: int) -> np.ndarray:
    """Polyphase resampling: each output phase is one short convolution of the input."""
    from math import gcd

    if rate == target or not len(pcm):
        return pcm.astype(np.int16)
    g = gcd(rate, target)
    up, down = target // g, rate // g
    taps = _kernel(up, down)
    mid, n_out = len(taps) // 2, -(-len(pcm) * up // down)
    x = pcm.astype(np.float32)
    out = np.empty(n_out, np.float32)
    for phase in range(up):
        # outputs k with k * down = phase (mod up) use the taps phase, phase + up, ...
        ks = np.arange((phase * pow(down, -1, up)) % up if up > 1 else 0, n_out, up)
        sub = taps[(mid + phase) % up :: up].astype(np.float32)
        lead = (mid + phase) // up
        full = np.convolve(x, sub)
        out[ks] = full[np.minimum(ks * down // up + lead, len(full) - 1)]
    return np.clip(np.rint(out), -32768, 32767).astype(np.int16)


def decode_media(df: DataFrame, media_col: str = "media", rate: int = 16_000) -> DataFrame:
    """``df`` with ``pcm`` (16-bit little-endian at ``rate``), ``pcm_rate`` and ``pcm_samples``."""

    @F.pandas_udf("struct<pcm:binary,pcm_rate:int,pcm_samples:long>")
    def run(media):
        import pandas as pd

        out = []
        for m in media:
            try:
                own, pcm = decode_wav(bytes(m)) if m is not None else (0, None)
            except ValueError:
                pcm = None
            if pcm is None:
                out.append((None, None, None))
            else:
                pcm = resample(pcm, own, rate)
                out.append((pcm.astype("<i2").tobytes(), rate, len(pcm)))
        return pd.DataFrame(out, columns=["pcm", "pcm_rate", "pcm_samples"])

    return df.withColumn("decoded", run(media_col)).select(*df.columns, "decoded.*")


def pad_payload(text: bytes, unit: int = 64) -> bytes:
    return text + b"\0" * (-len(text) % unit if text else unit)


UNIT = 64
IMA_BLOCK = 4 + UNIT  # a header and one unit of codes
CODECS = (MULAW, ALAW, IMA)


def store_payload(payload: bytes, codec: int = MULAW) -> bytes:
    """The payload as mu-law or A-law samples, or as the codes of ADPCM blocks that start from silence."""
    if codec != IMA:
        return wav(codec, payload, len(payload))
    codes = np.frombuffer(payload, np.uint8).reshape(-1, UNIT)
    data = np.hstack([np.zeros((len(codes), 4), np.uint8), codes]).tobytes()
    return wav(IMA, data, len(codes) * (2 * UNIT + 1), block=IMA_BLOCK)


def read_payload(media: bytes) -> bytes:
    """What ``store_payload`` was given."""
    codec, _, block, _, data = read_wav(media)
    return np.frombuffer(data, np.uint8).reshape(-1, block)[:, 4:].tobytes() if codec == IMA else data


def codec_of(payload: bytes) -> int:
    """Payloads are dealt over the codecs by their content, so equal ones are stored alike."""
    return CODECS[zlib.crc32(payload) % len(CODECS)]


def decode_many(files: list[bytes]) -> list[tuple[int, np.ndarray]]:
    """(rate, PCM) of each file; the ADPCM blocks of all of them are decoded together where they are of one size."""
    read = [read_wav(m) for m in files]
    out: list = [None] * len(files)
    by_block: dict[int, list[int]] = {}
    for i, (codec, rate, block, samples, data) in enumerate(read):
        if codec == IMA:
            by_block.setdefault(block, []).append(i)
        else:
            out[i] = rate, (np.frombuffer(data, "<i2", samples) if codec == PCM else TABLES[codec][np.frombuffer(data, np.uint8, samples)])
    for block, ids in by_block.items():
        per = (block - 4) * 2 + 1
        blocks = [len(read[i][4]) // block for i in ids]
        pcm = ima_decode(b"".join(read[i][4][: n * block] for i, n in zip(ids, blocks, strict=True)), block, sum(blocks) * per)
        at = 0
        for i, n in zip(ids, blocks, strict=True):
            out[i] = read[i][1], pcm[at : at + n * per][: read[i][3]]
            at += n * per
    return out


def features(rate: int, pcm: np.ndarray, up: np.ndarray, target: int) -> str:
    x = pcm.astype(np.float32)
    power = float(np.sqrt(np.dot(x, x) / len(x)))
    crossings = int(np.count_nonzero((pcm[1:] < 0) != (pcm[:-1] < 0)))
    return f"rate={rate};samples={len(pcm)};rms={power:.2f};peak={int(np.abs(x).max())};crossings={crossings};pcm{target}_samples={len(up)};pcm{target}_crc32={zlib.crc32(up.astype('<i2').tobytes())}"


NAMES = {MULAW: "mulaw", ALAW: "alaw", IMA: "ima_adpcm"}


def _stored(texts: list[bytes], rate: int) -> Iterator[tuple[int, bytes, int, np.ndarray, np.ndarray]]:
    """(codec, file, its rate, its PCM, resampled PCM) of each text."""
    payloads = [pad_payload(t, UNIT) for t in texts]
    codecs = [codec_of(p) for p in payloads]
    files = [store_payload(p, c) for p, c in zip(payloads, codecs, strict=True)]
    for c, media, (own, pcm) in zip(codecs, files, decode_many(files), strict=True):
        yield c, media, own, pcm, resample(pcm, own, rate)


def _texts(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list, list[bytes]]]:
    for whole in batches:
        for b in slices(whole):
            yield b.column(0).to_pylist(), [t.as_buffer().to_pybytes() if t.is_valid else b"" for t in b.column(1)]


def store_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rate: int = 16_000) -> DataFrame:
    """(doc_id, codec, media, pcm, pcm_rate): each text as a telephony file, and its sound as 16-bit PCM at ``rate``."""

    def run(batches):
        for ids, texts in _texts(batches):
            rows = [(NAMES[c], media, up.astype("<i2").tobytes()) for c, media, _, _, up in _stored(texts, rate)]
            names, files, pcm = (list(x) for x in zip(*rows, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(names), pa.array(files, pa.binary()), pa.array(pcm, pa.binary()), pa.array([rate] * len(ids), pa.int32())], ["doc_id", "codec", "media", "pcm", "pcm_rate"])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, codec string, media binary, pcm binary, pcm_rate int")


def media_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rate: int = 16_000) -> DataFrame:
    """One row per document: its text stored as telephony audio, read back, decoded, resampled and measured."""
    longs = ("doc_id", "n_bytes", "payload_bytes", "tail_crc32", "media_bytes")
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "codec"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, texts in _texts(batches):
            rows: list[list] = [[] for _ in names]
            for doc, raw, (codec, media, own, pcm, up) in zip(ids, texts, _stored(texts, rate), strict=True):
                back = read_payload(media)
                row = (doc, len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(media), hashlib.sha256(media).hexdigest(), features(own, pcm, up, rate), NAMES[codec])
                for r, x in zip(rows, row, strict=True):
                    r.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(r, pa.int64() if n in longs else pa.string()) for n, r in zip(names, rows, strict=True)], names)

    schema = ", ".join(f"{n} {'long' if n in longs else 'string'}" for n in names)
    return docs.select(F.col(id_col).cast("long"), F.col(text_col).alias("text")).mapInArrow(run, schema)
