"""Telephony audio columns: G.711 mu-law and A-law, IMA ADPCM, WAV storage, resampled PCM.

G.711 bytes expand by 256-entry tables; ADPCM steps through the samples of a block once and
works on all blocks of a batch side by side.
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

from phrasework.llm.textbytes import slices, utf8

#: Samples a second of the stored telephony form, and of the PCM made from it.
TELEPHONY_RATE, PCM_RATE = 8000, 16000
#: Payload bytes in an ADPCM block; a block also has a header of four bytes.
ADPCM_DATA = 64
CODECS = ("mulaw", "alaw", "ima_adpcm")
WAVE_FORMAT = {"pcm": 1, "alaw": 6, "mulaw": 7, "ima_adpcm": 17}

# The index changes of IMA ADPCM by code; the 89 step sizes follow.
INDEX_CHANGE = np.array([-1, -1, -1, -1, 2, 4, 6, 8] * 2, np.int32)
# The step sizes of IMA ADPCM, which no exact rule gives.
STEPS = np.array(
    [
        7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118,
        130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060,
        1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484,
        7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767,
    ],
    np.int32,
)


def mulaw_table() -> np.ndarray:
    """PCM value of each mu-law byte."""
    code = ~np.arange(256, dtype=np.int32) & 0xFF
    size = ((((code & 15) << 3) + 132) << ((code >> 4) & 7)) - 132
    return np.where(code & 128, -size, size).astype(np.int16)


def alaw_table() -> np.ndarray:
    """PCM value of each A-law byte."""
    code = np.arange(256, dtype=np.int32) ^ 0x55
    segment, low = (code >> 4) & 7, ((code & 15) << 4) + 8
    size = np.where(segment == 0, low, (low + 256) << np.maximum(segment - 1, 0))
    return np.where(code & 128, size, -size).astype(np.int16)


MULAW, ALAW = mulaw_table(), alaw_table()


def compress(pcm: np.ndarray, table: np.ndarray) -> np.ndarray:
    """The byte whose table value lies nearest to each PCM sample, on ties the smaller value."""
    order = np.argsort(table, kind="stable")
    values = table[order].astype(np.int32)
    middle = (values[1:] + values[:-1]) / 2
    return order[np.searchsorted(middle, pcm.astype(np.int32))].astype(np.uint8)


def decode_adpcm(blocks: np.ndarray) -> np.ndarray:
    """Decode mono IMA ADPCM blocks (one a row, header included) into int16 samples.

    A block gives its header's predictor and then two samples a byte, low half first.
    """
    n, width = blocks.shape
    value = blocks[:, 0].astype(np.int32) | (blocks[:, 1].astype(np.int32) << 8)
    value = np.where(value >= 1 << 15, value - (1 << 16), value)
    index = np.minimum(blocks[:, 2].astype(np.int32), 88)
    out = np.empty((2 * (width - 4) + 1, n), np.int16)
    out[0] = value
    data = np.ascontiguousarray(blocks[:, 4:].T)
    for k in range(2 * (width - 4)):
        code = ((data[k >> 1] >> (4 * (k & 1))) & 15).astype(np.int32)
        step = STEPS[index]
        change = step >> 3
        change = change + (step >> 2) * (code & 1) + (step >> 1) * ((code >> 1) & 1) + step * ((code >> 2) & 1)
        value = np.clip(np.where(code & 8, value - change, value + change), -32768, 32767)
        index = np.clip(index + INDEX_CHANGE[code], 0, 88)
        out[k + 1] = value
    return np.ascontiguousarray(out.T)


def encode_adpcm(pcm: np.ndarray, data: int = ADPCM_DATA) -> np.ndarray:
    """Encode int16 samples into blocks of ``data`` bytes each; the last block repeats its last sample."""
    each = 2 * data + 1
    n = max(1, -(-len(pcm) // each))
    pcm = np.concatenate([pcm, np.full(n * each - len(pcm), pcm[-1] if len(pcm) else 0, np.int16)]).reshape(n, each).astype(np.int32)
    value, index = pcm[:, 0].copy(), np.zeros(n, np.int32)
    blocks = np.zeros((n, data + 4), np.uint8)
    blocks[:, 0], blocks[:, 1] = value & 255, (value >> 8) & 255
    for k in range(2 * data):
        step, gap = STEPS[index], pcm[:, k + 1] - value
        code, size, change = np.where(gap < 0, 8, 0), np.abs(gap), step >> 3
        for bit, part in ((4, step), (2, step >> 1), (1, step >> 2)):
            hit = size >= part
            code, size, change = code | (bit * hit), size - part * hit, change + part * hit
        value = np.clip(np.where(code & 8, value - change, value + change), -32768, 32767)
        index = np.clip(index + INDEX_CHANGE[code], 0, 88)
        blocks[:, 4 + (k >> 1)] |= (code << (4 * (k & 1))).astype(np.uint8)
    return blocks


def resample_double(pcm: np.ndarray) -> np.ndarray:
    """Twice the rate: samples stay, between them a four-tap half-band filter in whole numbers."""
    if not len(pcm):
        return pcm.astype(np.int16)
    x = np.concatenate([pcm[:1], pcm, pcm[-1:], pcm[-1:]]).astype(np.int32)
    out = np.empty(2 * len(pcm), np.int16)
    out[::2] = pcm
    out[1::2] = np.clip((9 * (x[1:-2] + x[2:-1]) - x[:-3] - x[3:] + 8) >> 4, -32768, 32767)
    return out


def write_wav(codec: str, data: bytes, rate: int = TELEPHONY_RATE) -> bytes:
    """A mono WAV file of already encoded ``data``."""
    bits, align = {"pcm": (16, 2), "ima_adpcm": (4, ADPCM_DATA + 4)}.get(codec, (8, 1))
    per_block = 2 * ADPCM_DATA + 1 if codec == "ima_adpcm" else 1
    fmt = struct.pack("<HHIIHH", WAVE_FORMAT[codec], 1, rate, rate * align // per_block, align, bits)
    if codec != "pcm":
        extra = struct.pack("<H", per_block) if codec == "ima_adpcm" else b""
        fmt += struct.pack("<H", len(extra)) + extra
    body = b"WAVEfmt " + struct.pack("<I", len(fmt)) + fmt + b"data" + struct.pack("<I", len(data)) + data
    body += b"\0" * (len(data) & 1)
    return b"RIFF" + struct.pack("<I", len(body)) + body


def read_wav(media: bytes) -> tuple[str, int, bytes]:
    """Codec, rate and encoded data of a WAV file; raises ValueError on other input."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, codec, rate = 12, None, 0
    while at + 8 <= len(media):
        name, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if name == b"fmt ":
            kind, _, rate = struct.unpack_from("<HHI", media, at + 8)
            codec = next((k for k, v in WAVE_FORMAT.items() if v == kind), None)
        elif name == b"data" and codec:
            return codec, rate, media[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    raise ValueError("no sound data")


def pack_payload(codec: str, payload: bytes) -> bytes:
    """Store a payload of whole 64-byte groups without loss: as 8-bit samples, or as ADPCM codes."""
    if codec == "ima_adpcm":
        blocks = np.zeros((len(payload) // ADPCM_DATA, ADPCM_DATA + 4), np.uint8)
        blocks[:, 4:] = np.frombuffer(payload, np.uint8).reshape(-1, ADPCM_DATA)
        payload = blocks.tobytes()
    return write_wav(codec, payload)


def unpack_payload(media: bytes) -> bytes:
    """The payload read back from its stored form."""
    codec, _, data = read_wav(media)
    if codec == "ima_adpcm":
        return np.frombuffer(data, np.uint8).reshape(-1, ADPCM_DATA + 4)[:, 4:].tobytes()
    return data


def decode(media: bytes) -> np.ndarray:
    """PCM samples of a stored clip at its own rate."""
    codec, _, data = read_wav(media)
    raw = np.frombuffer(data, np.uint8)
    if codec == "pcm":
        return np.frombuffer(data, "<i2")
    if codec == "ima_adpcm":
        return decode_adpcm(raw.reshape(-1, ADPCM_DATA + 4)).reshape(-1)
    return (MULAW if codec == "mulaw" else ALAW)[raw]


def features(pcm: np.ndarray) -> str:
    """Whole-number features of PCM: samples, peak, mean square, mean, zero crossings."""
    if not len(pcm):
        return "samples=0;peak=0;mean_square=0;mean=0;crossings=0"
    x = pcm.astype(np.int64)
    crossings = int(np.count_nonzero((pcm[1:] < 0) != (pcm[:-1] < 0)))
    return f"samples={len(x)};peak={int(np.abs(x).max())};mean_square={int((x * x).sum() // len(x))};mean={int(x.sum() // len(x))};crossings={crossings}"


def text_payload(text: bytes) -> bytes:
    """UTF-8 bytes with zero bytes up to a positive multiple of 64."""
    return text + b"\0" * (-len(text) % 64 if text else 64)


def codec_of(payload: bytes) -> str:
    """A codec chosen by the payload alone, so that equal texts are stored alike."""
    return CODECS[zlib.crc32(payload) % len(CODECS)]


CLIP = pa.schema(
    [("id", pa.int64()), ("codec", pa.string()), ("n_bytes", pa.int64()), ("payload", pa.binary()), ("media", pa.binary()), ("pcm_wav", pa.binary())]
)
DIGEST_TYPE = "id bigint, codec string, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, pcm_bytes long, pcm_sha256 string, feature string"


def _clip(text: bytes, codec: str | None):
    payload = text_payload(text)
    codec = codec or codec_of(payload)
    media = pack_payload(codec, payload)
    return codec, len(text), unpack_payload(media), media


def text_to_clips(docs: DataFrame, codec: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store each whole text as a clip: (id, codec, n_bytes, payload, media, pcm_wav).

    ``media`` is a WAV file in ``codec`` (by the text's own checksum if none is given),
    ``payload`` what is read back from it, ``pcm_wav`` 16-bit PCM at 16 kHz. A null text
    counts as empty and gives 64 zero bytes; null ids and repeated rows stay.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                raw, at = utf8(batch.column("text"))
                clips = [_clip(raw[a:b].tobytes(), codec) for a, b in zip(at[:-1], at[1:])]
                wavs = [write_wav("pcm", resample_double(decode(m)).tobytes(), PCM_RATE) for _, _, _, m in clips]
                kinds, sizes, payloads, medias = zip(*clips)
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(kinds), pa.array(sizes), pa.array(payloads), pa.array(medias), pa.array(wavs)], schema=CLIP)

    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "id bigint, codec string, n_bytes bigint, payload binary, media binary, pcm_wav binary")


def clip_digests(docs: DataFrame, codec: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Digests and features of what :func:`text_to_clips` stores, made where the clips are.

    The clips of a batch are stored, read back, decoded, resampled and measured together and
    only digests leave the executor. Nulls and repeats as in :func:`text_to_clips`.
    """
    names = [x.split()[0] for x in DIGEST_TYPE.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                raw, at = utf8(batch.column("text"))
                clips = [_clip(raw[a:b].tobytes(), codec) for a, b in zip(at[:-1], at[1:])]
                sounds: list[np.ndarray] = [np.zeros(0, np.int16)] * len(clips)
                blocked = [i for i, c in enumerate(clips) if c[0] == "ima_adpcm"]
                for i, c in enumerate(clips):
                    if c[0] != "ima_adpcm":
                        sounds[i] = decode(c[3])
                if blocked:  # one pass over the blocks of all clips
                    data = [np.frombuffer(read_wav(clips[i][3])[2], np.uint8).reshape(-1, ADPCM_DATA + 4) for i in blocked]
                    done = decode_adpcm(np.concatenate(data))
                    for i, part in zip(blocked, np.split(done, np.cumsum([len(x) for x in data])[:-1])):
                        sounds[i] = part.reshape(-1)
                columns: list[list] = [[] for _ in names[1:]]
                for (kind, size, payload, media), pcm in zip(clips, sounds):
                    wav = write_wav("pcm", resample_double(pcm).tobytes(), PCM_RATE)
                    row = (kind, size, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(media), hashlib.sha256(media).hexdigest(), len(wav), hashlib.sha256(wav).hexdigest(), f"codec={kind};rate={TELEPHONY_RATE};{features(pcm)}")
                    for column, value in zip(columns, row):
                        column.append(value)
                yield pa.RecordBatch.from_arrays([batch.column("id"), *map(pa.array, columns)], names=names)

    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, DIGEST_TYPE)
