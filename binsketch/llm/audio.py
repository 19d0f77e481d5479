"""Telephony audio columns: mu-law, A-law and block ADPCM, decoded in numpy."""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
from pyspark.sql import DataFrame

from .common import map_batches, texts_of

#: Fixed values of the 4-bit ADPCM format: step sizes, and how a code moves the step index.
STEPS = np.array([7, 8, 9, 10, 11, 12, 13, 14, 16, 17, 19, 21, 23, 25, 28, 31, 34, 37, 41, 45, 50, 55, 60, 66, 73, 80, 88, 97, 107, 118, 130, 143, 157, 173, 190, 209, 230, 253, 279, 307, 337, 371, 408, 449, 494, 544, 598, 658, 724, 796, 876, 963, 1060, 1166, 1282, 1411, 1552, 1707, 1878, 2066, 2272, 2499, 2749, 3024, 3327, 3660, 4026, 4428, 4871, 5358, 5894, 6484, 7132, 7845, 8630, 9493, 10442, 11487, 12635, 13899, 15289, 16818, 18500, 20350, 22385, 24623, 27086, 29794, 32767], np.int32)
MOVES = np.array([-1, -1, -1, -1, 2, 4, 6, 8], np.int32)
#: Fixed values of the container: format tags.
TAGS = {"mulaw": 7, "alaw": 6, "adpcm": 17}
BLOCK = 64


def mulaw_table() -> np.ndarray:
    """int16 value of each mu-law byte."""
    code = ~np.arange(256) & 255
    magnitude = (((code & 15) << 3) + 132 << ((code >> 4) & 7)) - 132
    return np.where(code & 128, -magnitude, magnitude).astype(np.int16)


def alaw_table() -> np.ndarray:
    """int16 value of each A-law byte."""
    code = np.arange(256) ^ 0x55
    segment, low = code >> 4 & 7, (code & 15) << 4
    magnitude = np.where(segment == 0, low + 8, low + 264 << np.maximum(segment - 1, 0))
    return np.where(code & 128, magnitude, -magnitude).astype(np.int16)


TABLES = {"mulaw": mulaw_table(), "alaw": alaw_table()}


def adpcm_decode(data: np.ndarray, block: int = BLOCK) -> np.ndarray:
    """int16 samples, one row for each block of ``block`` bytes.

    A block begins with a 16-bit sample, a step index (beyond 88: 88) and a
    reserved byte; then two codes a byte, the low one first. All blocks advance
    together, one sample a step.
    """
    rows = data.reshape(-1, block)
    out = np.empty((1 + 2 * (block - 4), len(rows)), np.int16)
    value = np.ascontiguousarray(rows[:, :2]).view("<i2").ravel().astype(np.int32)
    index = np.minimum(rows[:, 2].astype(np.int32), 88)
    out[0] = value
    codes = np.ascontiguousarray(rows[:, 4:].T)
    for k in range(codes.shape[0]):
        for half in (0, 1):
            code = codes[k] >> 4 * half & 15
            step = STEPS[index]
            change = step >> 3
            change += np.where(code & 1, step >> 2, 0)
            change += np.where(code & 2, step >> 1, 0)
            change += np.where(code & 4, step, 0)
            value = np.clip(np.where(code & 8, value - change, value + change), -32768, 32767)
            index = np.clip(index + MOVES[code & 7], 0, 88)
            out[1 + 2 * k + half] = value
    return out.T


def resampled(pcm: np.ndarray, up: int, down: int, at_once: int = 1 << 20) -> np.ndarray:
    """Linear interpolation at ``up/down`` times the rate, in whole numbers (rounded down), so that it is the same everywhere."""
    if not len(pcm):
        return pcm.astype(np.int16)
    out = np.empty((len(pcm) * up - 1) // down + 1, np.int16)
    for i in range(0, len(out), at_once):  # which bounds the memory
        at = np.arange(i, min(i + at_once, len(out)), dtype=np.int64) * down
        left, part = at // up, at % up
        a, b = pcm[left].astype(np.int64), pcm[np.minimum(left + 1, len(pcm) - 1)].astype(np.int64)
        out[i : i + at_once] = (a * (up - part) + b * part) // up
    return out


def container(payload: bytes, codec: str, rate: int = 8000, block: int = BLOCK) -> bytes:
    """A RIFF/WAVE file that holds ``payload`` as it is: one sample a byte, or ADPCM blocks."""
    per_block = 1 + 2 * (block - 4)
    if codec == "adpcm":
        fmt = struct.pack("<HHIIHHHH", TAGS[codec], 1, rate, rate * block // per_block, block, 4, 2, per_block)
        samples = len(payload) // block * per_block
    else:
        fmt, samples = struct.pack("<HHIIHHH", TAGS[codec], 1, rate, rate, 1, 8, 0), len(payload)
    fact = struct.pack("<I", samples)
    chunks = b"".join(tag + struct.pack("<I", len(x)) + x + b"\0" * (len(x) % 2) for tag, x in ((b"fmt ", fmt), (b"fact", fact), (b"data", payload)))
    return b"RIFF" + struct.pack("<I", 4 + len(chunks)) + b"WAVE" + chunks


def parsed(media: bytes) -> tuple[str, int, bytes]:
    """codec, rate and payload of a file; ValueError if it is none of ours."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a RIFF/WAVE file")
    at, codec, rate = 12, None, 0
    while at + 8 <= len(media):
        tag, n = media[at : at + 4], int.from_bytes(media[at + 4 : at + 8], "little")
        if tag == b"fmt ":
            kind, _, rate = struct.unpack_from("<HHI", media, at + 8)
            codec = {v: k for k, v in TAGS.items()}.get(kind)
        elif tag == b"data" and codec:
            return codec, rate, media[at + 8 : at + 8 + n]
        at += 8 + n + n % 2
    raise ValueError("no telephony audio in the file")


def pcm_of(files: list[bytes | None]) -> list[tuple[np.ndarray | None, int, bytes, str | None]]:
    """int16 samples, rate, payload and error of each file; the ADPCM blocks of all files are decoded together."""
    out: list = [(None, 0, b"", "no file")] * len(files)
    blocks: list[tuple[int, np.ndarray]] = []
    for i, media in enumerate(files):
        try:
            codec, rate, payload = parsed(media or b"")
        except (ValueError, struct.error) as e:
            out[i] = None, 0, b"", str(e)
            continue
        data = np.frombuffer(payload, np.uint8)
        if codec == "adpcm":
            blocks.append((i, data[: len(data) // BLOCK * BLOCK]))
        out[i] = None if codec == "adpcm" else TABLES[codec][data], rate, payload, None
    if blocks:
        samples = adpcm_decode(np.concatenate([d for _, d in blocks]))
        cuts = np.cumsum([len(d) // BLOCK for _, d in blocks])[:-1]
        for (i, _), own in zip(blocks, np.split(samples, cuts), strict=True):
            out[i] = own.ravel(), *out[i][1:]
    return out


def decoded(audio: DataFrame, id_col: str = "doc_id", media_col: str = "media", rate: int = 16000) -> DataFrame:
    """One row per file: id, n_samples, pcm (16-bit little-endian binary at ``rate``), error.

    Null or foreign media: null pcm and an error text, never a failed task.
    Repeated rows stay; other columns are ignored.
    """

    def run(batch):
        out = {k: [] for k in ("n_samples", "pcm", "error")}
        for pcm, own, _, error in pcm_of(batch.column(media_col).to_pylist()):
            if pcm is not None:
                g = np.gcd(own, rate)
                pcm = resampled(pcm, int(rate // g), int(own // g))
            out["n_samples"].append(None if pcm is None else len(pcm))
            out["pcm"].append(None if pcm is None else pcm.astype("<i2").tobytes())
            out["error"].append(error)
        yield {id_col: batch.column(id_col)} | out

    return map_batches(audio.select(id_col, media_col), run, f"{id_col} long, n_samples long, pcm binary, error string")


def codec_of(payload: bytes) -> str:
    """One of the formats, by the payload alone: equal payloads are stored alike."""
    return sorted(TAGS)[zlib.crc32(payload) % len(TAGS)]


def padded(raw: bytes) -> bytes:
    return raw + b"\0" * (max(BLOCK, -(-len(raw) // BLOCK) * BLOCK) - len(raw))


def stored(docs: DataFrame, codec: str | None = None, id_col: str = "doc_id", text_col: str = "text", rate: int = 8000) -> DataFrame:
    """Each text's bytes, with zeros up to a positive multiple of 64, as the samples (or ADPCM blocks) of one file: id, n_bytes, media.

    Without a ``codec`` each payload gets one of the three by its checksum, as in a
    mixed collection. Null or empty text: 64 zero bytes. Repeated rows stay; other
    columns are ignored.
    """

    def run(batch):
        raw = [t.encode() for t in texts_of(batch, text_col)]
        payloads = [padded(r) for r in raw]
        yield {id_col: batch.column(id_col), "n_bytes": [len(r) for r in raw], "media": [container(p, codec or codec_of(p), rate) for p in payloads]}

    return map_batches(docs.select(id_col, text_col), run, f"{id_col} long, n_bytes long, media binary")


def features(pcm: np.ndarray, at_once: int = 1 << 20) -> str:
    """Peak, energy (sum of squares), sign changes and a checksum of 16-bit samples, as text."""
    negative, peak, energy = pcm < 0, 0, 0
    for i in range(0, len(pcm), at_once):
        wide = pcm[i : i + at_once].astype(np.int64)
        peak, energy = max(peak, int(np.abs(wide).max())), energy + int(wide @ wide)
    return f"n={len(pcm)};peak={peak};energy={energy};turns={int(np.count_nonzero(negative[1:] != negative[:-1]))};crc={zlib.crc32(pcm.astype('<i2').tobytes())}"


def media_digests(media: DataFrame, id_col: str = "doc_id", rate: int = 16000, with_pcm: bool = False) -> DataFrame:
    """Reads ``stored`` files back: id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature,
    codec, and with ``with_pcm`` the resampled samples (pcm, 16-bit little-endian, a row of 2 GB at most) for the caller to store.

    The feature is that of the resampled samples. Empty tables give no rows.
    """

    def run(batch):
        names = ("payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "codec", "pcm")
        out = {k: [] for k in names}
        files = batch.column("media").to_pylist()
        for blob, (pcm, own, payload, error) in zip(files, pcm_of(files), strict=True):
            if error:
                raise ValueError(error)
            g = int(np.gcd(own, rate))
            pcm = resampled(pcm, rate // g, own // g)
            found = (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-BLOCK:]), len(blob), hashlib.sha256(blob).hexdigest(), features(pcm), parsed(blob)[0], pcm.astype("<i2").tobytes() if with_pcm else None)
            for k, v in zip(names, found, strict=True):
                out[k].append(v)
        yield {id_col: batch.column(id_col), "n_bytes": batch.column("n_bytes")} | out

    return map_batches(media, run, f"{id_col} long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, codec string" + ", pcm binary" * with_pcm)
