"""Bytes as 8-bit mono FLAC: encoding, and decoding into PCM blocks with seekable sample offsets.

Frames of many documents are handled in step: sample i of all of them at once, so that the sequential parts of the
format (unary Rice quotients, linear prediction, checksums) cost a few array operations for each i and not for each
sample. A stream has a seek point for every frame, so the reader can start all frames together.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusloom.runtime import ensure_importable

BLOCK = 576  # samples of a frame; the format's code for it is 2
RATE = 8000
FRAMES = 2048  # handled in step
#: Fixed values of the format: coefficients of its fixed predictors, by order.
FIXED = ((), (1,), (2, -1), (3, -3, 1), (4, -6, 4, -1))


def _crc_table(poly: int, bits: int) -> np.ndarray:
    table = np.arange(256, dtype=np.uint32) << (bits - 8)
    for _ in range(8):
        table = np.where(table >> (bits - 1) & 1, (table << 1) ^ poly, table << 1) & ((1 << bits) - 1)
    return table


CRC8, CRC16 = _crc_table(0x07, 8), _crc_table(0x8005, 16)


def _crcs(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray, table: np.ndarray, bits: int) -> np.ndarray:
    """Checksums of data[start : start + size] for all starts, byte by byte in step."""
    crc = np.zeros(len(starts), np.uint32)
    order = np.argsort(-sizes, kind="stable")
    starts, sizes = starts[order], sizes[order]
    live = np.searchsorted(-sizes, -np.arange(1, int(sizes[0]) + 1), side="right") if len(sizes) else []
    for i, n in enumerate(live):
        crc[:n] = ((crc[:n] << 8) & ((1 << bits) - 1)) ^ table[(crc[:n] >> (bits - 8)) ^ data[starts[:n] + i]]
    out = np.empty_like(crc)
    out[order] = crc
    return out


def _number(n: int) -> bytes:
    """A frame number in the format's variable length, which extends UTF-8."""
    if n < 0x80:
        return bytes([n])
    tail = []
    while n >= 1 << (6 - len(tail)):
        tail.insert(0, 0x80 | (n & 0x3F))
        n >>= 6
    return bytes([(0xFF << (7 - len(tail))) & 0xFF | n, *tail])


def _zigzag(x: np.ndarray) -> np.ndarray:
    return np.where(x < 0, -2 * x - 1, 2 * x)


def _rice_cost(u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The best parameter of each row, and its bits."""
    n = u.shape[1]
    near = np.log2(np.maximum(u.mean(1), 1)).astype(np.int64)
    best, cost = near.copy(), np.full(len(u), 1 << 40)
    for d in (-1, 0, 1):
        k = np.clip(near + d, 0, 14)
        bits = (u >> k[:, None]).sum(1) + n * (k + 1)
        best, cost = np.where(bits < cost, k, best), np.minimum(cost, bits)
    return best, cost


def encode_frames(samples: np.ndarray, numbers: np.ndarray) -> list[bytes]:
    """Frames of rows of signed 8-bit samples. Each takes the cheapest of a constant, a fixed predictor, or the samples as they are."""
    f = len(samples)
    x = samples.astype(np.int32)
    flat = (x == x[:, :1]).all(1)
    residual, order, param, cost = np.zeros_like(x), np.zeros(f, np.int64), np.zeros(f, np.int64), np.full(f, 1 << 40)
    diff = x
    for o in range(4):
        u = _zigzag(diff[:, o:] if o else diff)
        k, bits = _rice_cost(u)
        better = bits + 8 * o < cost
        residual[better, o:] = u[better]
        order[better], param[better], cost[better] = o, k[better], bits[better] + 8 * o
        diff = np.concatenate((diff[:, :1] * 0, np.diff(diff, axis=1)), axis=1)
    plain = (cost + 10 >= 8 * BLOCK) & ~flat
    coded = ~flat & ~plain
    heads = [b"\xff\xf8\x20\x02" + _number(int(n)) for n in numbers]
    head_size = np.fromiter(map(len, heads), np.int64, f) + 1
    body_bits = 8 + np.where(flat, 8, np.where(plain, 8 * BLOCK, cost + 10))
    sizes = head_size + (body_bits + 7) // 8 + 2
    starts = np.cumsum(sizes) - sizes
    bits = np.zeros(int(sizes.sum()) * 8, np.uint8)
    at = (starts + head_size) * 8

    def put(where: np.ndarray, value: np.ndarray, width: int) -> None:
        for j in range(width):
            bits[where + j] = (value >> (width - 1 - j)) & 1

    put(at, np.where(flat, 0, np.where(plain, 2, 16 + 2 * order)), 8)
    put(at[flat] + 8, x[flat, 0] & 255, 8)
    put((at[plain] + 8)[:, None] + 8 * np.arange(BLOCK), x[plain] & 255, 8)
    for o in range(1, 4):
        some = coded & (order == o)
        put((at[some] + 8)[:, None] + 8 * np.arange(o), x[some, :o] & 255, 8)
    put(at[coded] + 8 + 8 * order[coded] + 6, param[coded], 4)  # six zero bits: plain Rice codes, one partition
    for k in np.unique(param[coded]):
        for o in range(4):
            some = np.flatnonzero(coded & (param == k) & (order == o))
            if not len(some):
                continue
            u = residual[some, o:]
            q = u >> k
            stop = np.cumsum(q + 1 + k, axis=1) - 1 - k + (at[some] + 18 + 8 * o)[:, None]
            bits[stop] = 1
            for j in range(k):
                bits[stop + 1 + j] = (u >> (k - 1 - j)) & 1
    data = np.packbits(bits)
    joined, places = np.frombuffer(b"".join(heads), np.uint8), head_size - 1
    inside = np.arange(len(joined)) - np.repeat(np.cumsum(places) - places, places)
    data[np.repeat(starts, places) + inside] = joined
    data[starts + head_size - 1] = _crcs(data, starts, head_size - 1, CRC8, 8)
    crc = _crcs(data, starts, sizes - 2, CRC16, 16)
    data[starts + sizes - 2], data[starts + sizes - 1] = crc >> 8, crc & 255
    whole = data.tobytes()
    return [whole[a : a + n] for a, n in zip(starts.tolist(), sizes.tolist(), strict=True)]


def encode(payloads: list[bytes], rate: int = RATE) -> list[bytes]:
    """FLAC streams of payloads whose sizes are positive multiples of BLOCK."""
    counts = [len(p) // BLOCK for p in payloads]
    numbers = np.concatenate([np.arange(n) for n in counts])
    samples = (np.frombuffer(b"".join(payloads), np.uint8) ^ 128).view(np.int8).reshape(-1, BLOCK)
    frames = [f for a in range(0, len(samples), FRAMES) for f in encode_frames(samples[a : a + FRAMES], numbers[a : a + FRAMES])]
    out, done = [], 0
    for payload, n in zip(payloads, counts, strict=True):
        own = frames[done : done + n]
        sizes = np.fromiter(map(len, own), np.int64, n)
        points = np.empty(n, [("sample", ">u8"), ("byte", ">u8"), ("samples", ">u2")])
        points["sample"], points["byte"], points["samples"] = np.arange(n) * BLOCK, np.cumsum(sizes) - sizes, BLOCK
        md5 = hashlib.md5((np.frombuffer(payload, np.uint8) ^ 128).tobytes()).digest()
        info = struct.pack(">HH", BLOCK, BLOCK) + int(sizes.min()).to_bytes(3, "big") + int(sizes.max()).to_bytes(3, "big")
        info += (rate << 44 | 7 << 36 | n * BLOCK).to_bytes(8, "big") + md5
        seek = points.tobytes()
        # A seek table over the format's 24-bit size holds as many points as fit; the reader finds the other frames by their sizes.
        seek = seek[: (2**24 - 1) // 18 * 18]
        out.append(b"fLaC\x00\x00\x00\x22" + info + b"\x83" + len(seek).to_bytes(3, "big") + seek + b"".join(own))
        done += n
    return out


@dataclass
class Stream:
    """Where a stream's frames are."""

    starts: np.ndarray  # bytes from the stream's begin
    samples: int
    md5: bytes


def parse(media: bytes) -> Stream:
    """Metadata of a stream with a seek point for each frame, or as many as a seek table holds."""
    if media[:4] != b"fLaC":
        raise ValueError("not a FLAC stream")
    at, last, total, md5, points = 4, False, 0, b"", np.zeros(0, np.int64)
    while not last:
        last, kind, size = bool(media[at] >> 7), media[at] & 127, int.from_bytes(media[at + 1 : at + 4], "big")
        body = media[at + 4 : at + 4 + size]
        if kind == 0:
            total, md5 = int.from_bytes(body[10:18], "big") & (1 << 36) - 1, body[18:34]
        elif kind == 3:
            points = np.frombuffer(body, [("sample", ">u8"), ("byte", ">u8"), ("samples", ">u2")])["byte"].astype(np.int64)
        at += 4 + size
    starts = points + at
    need = total // BLOCK
    if len(starts) < need:  # beyond the seek table: the next sync code whose header checksum holds and whose number follows
        more, data = starts.tolist(), np.frombuffer(media, np.uint8)
        where = more[-1] + 1
        while len(more) < need:
            head = b"\xff\xf8\x20\x02" + _number(len(more))
            where = media.index(head, where)
            if _crcs(data, np.array([where]), np.array([len(head)]), CRC8, 8)[0] == media[where + len(head)]:
                more.append(where)
            where += 1
        starts = np.array(more)
    return Stream(starts, total, md5)


def decode_frames(data: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """Rows of signed samples of the frames data[start:stop]; raises if a checksum is wrong.

    Handles constant, verbatim, fixed and linear predictors, both Rice methods, partitions and escaped partitions.
    """
    f = len(starts)
    first = data[starts + 4]
    extra = np.select([first < 0x80, first < 0xE0, first < 0xF0, first < 0xF8, first < 0xFC, first < 0xFE], [0, 1, 2, 3, 4, 5], 6)
    head = 5 + extra
    if (data[starts] != 0xFF).any() or (data[starts + 1] != 0xF8).any() or (data[starts + 2] != 0x20).any() or (_crcs(data, starts, head, CRC8, 8) != data[starts + head]).any():
        raise ValueError("bad frame header")
    crc = _crcs(data, starts, stops - 2 - starts, CRC16, 16)
    if (crc != (data[stops - 2].astype(np.uint32) << 8 | data[stops - 1])).any():
        raise ValueError("bad frame checksum")
    lo = int(starts.min())
    view = np.concatenate((data[lo : int(stops.max())], np.zeros(8, np.uint8)))
    word = view[:-4].astype(np.uint32) << 24 | view[1:-3].astype(np.uint32) << 16 | view[2:-2].astype(np.uint32) << 8 | view[3:-1]
    bits = np.unpackbits(view)
    ones = np.where(bits, np.arange(len(bits), dtype=np.int32), np.int32(len(bits)))
    ones = np.minimum.accumulate(ones[::-1])[::-1]
    pos = (starts - lo + head + 1) * 8

    def read(who, width):
        """Up to 25 bits of each frame in who; moves on."""
        p = pos[who]
        value = (word[p >> 3].astype(np.int64) >> (32 - width - (p & 7))) & ((1 << width) - 1)
        pos[who] = p + width
        return value

    def signed(value, width):
        return value - ((value >> (width - 1) & 1) << width) if np.ndim(width) == 0 else np.where(width > 0, value - ((value >> np.maximum(width - 1, 0) & 1) << width), 0)

    every = np.arange(f)
    kind = read(every, 8) >> 1
    x = np.zeros((f, BLOCK), np.int64)
    flat, plain = np.flatnonzero(kind == 0), np.flatnonzero(kind == 1)
    if len(flat):
        x[flat] = signed(read(flat, 8), 8)[:, None]
    if len(plain):
        p = (pos[plain] >> 3)[:, None] + np.arange(BLOCK)
        x[plain] = view[p].view(np.int8)
    order = np.where(kind >= 32, kind - 31, kind - 8)
    coded = np.flatnonzero(kind >= 8)
    if not len(coded):
        return x
    for i in range(int(order[coded].max())):
        some = coded[order[coded] > i]
        x[some, i] = signed(read(some, 8), 8)
    coefs, shift = np.zeros((f, 32), np.int64), np.zeros(f, np.int64)
    for o in range(1, 5):
        coefs[kind == 8 + o, :o] = FIXED[o]
    linear = np.flatnonzero(kind >= 32)
    if len(linear):
        precision = read(linear, 4) + 1
        shift[linear] = read(linear, 5)
        for i in range(int(order[linear].max())):
            on = order[linear] > i
            coefs[linear[on], i] = signed(read(linear[on], precision[on]), precision[on])
    method = np.zeros(f, np.int64)
    method[coded] = 4 + read(coded, 2)  # bits of a parameter
    span = np.zeros(f, np.int64)
    span[coded] = BLOCK >> read(coded, 4)
    k, raw = np.zeros(f, np.int64), np.full(f, -1)
    for i in range(BLOCK):
        on = coded[order[coded] <= i]
        new = on[(i == order[on]) | (i % span[on] == 0)]
        if len(new):
            k[new] = read(new, method[new])
            odd = new[k[new] == (1 << method[new]) - 1]
            raw[new] = -1
            if len(odd):
                raw[odd] = read(odd, 5)
        rice = on[raw[on] < 0]
        p = pos[rice]
        end = ones[p].astype(np.int64)
        pos[rice] = end + 1
        u = ((end - p) << k[rice]) | read(rice, k[rice])
        x[rice, i] = (u >> 1) ^ -(u & 1)
        if len(rice) < len(on):
            odd = on[raw[on] >= 0]
            x[odd, i] = signed(read(odd, raw[odd]), raw[odd])
    for o in range(1, 5):  # fixed predictors are repeated sums
        some = np.flatnonzero(kind == 8 + o)
        if len(some):
            d = x[some]
            warm = [d[:, :o].copy()]
            for _ in range(o):
                warm.append(np.diff(warm[-1], axis=1))
            part = d[:, o:]
            for level in range(o - 1, -1, -1):
                part = np.cumsum(part, axis=1) + warm[level][:, -1:]
            x[some, o:] = part
    if len(linear):
        top = int(order[linear].max())
        for i in range(1, BLOCK):
            on = linear[order[linear] <= i]
            back = min(i, top)
            guess = (x[on, i - back : i][:, ::-1] * coefs[on, :back]).sum(1)
            x[on, i] += guess >> shift[on]
    return x


def decode(streams: list[bytes]) -> Iterator[tuple[bytes, Stream]]:
    """PCM bytes (unsigned) and frame places of each stream; frame checksums and the stream's own digest must hold."""
    parsed = [parse(m) for m in streams]
    base = np.cumsum([0, *map(len, streams)])
    data = np.frombuffer(b"".join(streams), np.uint8)
    starts = np.concatenate([p.starts + b for p, b in zip(parsed, base, strict=False)])
    stops = np.concatenate([np.append(p.starts[1:], len(m)) + b for p, m, b in zip(parsed, streams, base, strict=False)])
    blocks = []
    for a in range(0, len(starts), FRAMES):
        blocks.append((decode_frames(data, starts[a : a + FRAMES], stops[a : a + FRAMES]).astype(np.int8).view(np.uint8)).tobytes())
    signed, at = b"".join(blocks), 0
    for p in parsed:
        own = signed[at : at + p.samples]
        at += p.samples
        if hashlib.md5(own).digest() != p.md5:
            raise ValueError("decoded samples differ from the stream's digest")
        yield (np.frombuffer(own, np.uint8) ^ 128).tobytes(), p


def payload(text: str | None) -> bytes:
    raw = (text or "").encode()
    return raw + b"\xff" * (-len(raw) % BLOCK or (0 if raw else BLOCK))


def feature(pcm: bytes) -> str:
    """Peak, energy, sign changes and summed steps of the signed samples."""
    x = (np.frombuffer(pcm, np.uint8) ^ 128).view(np.int8).astype(np.int32)
    return f"peak={int(np.abs(x).max())};energy={int((x * x).sum(dtype=np.int64))};turns={int(((x[1:] ^ x[:-1]) < 0).sum())};steps={int(np.abs(np.diff(x)).sum(dtype=np.int64))}"


def _groups(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple[list, list[str]]]:
    from corpusloom.llm.vocab import blocks

    for keys, texts in blocks(batches, size):
        yield keys, texts


def media_column(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, media): each text's UTF-8 bytes, padded with 255 to a positive multiple of 576, as a FLAC stream."""
    ensure_importable(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for keys, texts in _groups(batches, FRAMES * BLOCK):
            yield pa.RecordBatch.from_arrays([keys, pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(encode([payload(t) for t in texts]), pa.binary())], names=["doc_id", "n_bytes", "media"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, n_bytes long, media binary")


def pcm_blocks(media: DataFrame, frames: int = 16) -> DataFrame:
    """(doc_id, first_sample, n_samples, byte_offset, pcm): decoded blocks of so many frames, each with where to seek to."""
    ensure_importable(media.sparkSession)
    kind = media.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for key, m in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                [(pcm, stream)] = decode([m.as_py()])
                at = list(range(0, len(stream.starts), frames))
                own = [pcm[a * BLOCK : (a + frames) * BLOCK] for a in at]
                yield pa.RecordBatch.from_arrays([pa.array([key] * len(at), batch.schema.field(0).type), pa.array([a * BLOCK for a in at], pa.int64()), pa.array(list(map(len, own)), pa.int64()), pa.array(stream.starts[at], pa.int64()), pa.array(own, pa.binary())], names=["doc_id", "first_sample", "n_samples", "byte_offset", "pcm"])

    return media.select("doc_id", "media").mapInArrow(run, f"doc_id {kind}, first_sample long, n_samples long, byte_offset long, pcm binary")


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature), one row a row of docs.

    Each stream is encoded, decoded from the stored bytes and checked; digests of the payload are of what was read back.
    """
    ensure_importable(docs.sparkSession)
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for keys, texts in _groups(batches, FRAMES * BLOCK):
            media = encode([payload(t) for t in texts])
            back = [pcm for pcm, _ in decode(media)]
            yield pa.RecordBatch.from_arrays(
                [
                    keys, pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array([len(x) for x in back], pa.int64()),
                    pa.array([hashlib.sha256(x).hexdigest() for x in back]), pa.array([zlib.crc32(x[-32:]) for x in back], pa.int64()),
                    pa.array([len(m) for m in media], pa.int64()), pa.array([hashlib.sha256(m).hexdigest() for m in media]), pa.array([feature(x) for x in back]),
                ],
                names=names,
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
