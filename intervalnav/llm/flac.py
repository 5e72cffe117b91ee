"""FLAC (8-bit mono, fixed block size): vectorised encoder and decoder over many streams at once.

Every frame is one lane of the NumPy code: the encoder tries the fixed predictors of order 0 to 2 and a
linear predictor of order 2, and takes verbatim samples where Rice codes would not be shorter; the decoder
finds the frames through the seek table, verifies both checksums of each, decodes the Rice residuals of all
lanes in step and runs the predictors. Frames in forms that the encoder does not write (more partitions,
escapes, wasted bits, higher orders with wide codes) go through the scalar decoder.

Defined cases: a null text counts as empty; payloads are padded with zeros to a positive multiple of 64
bytes, so every stream has a sample; equal payloads give equal streams; a frame whose checksum or sync code
does not fit raises ``ValueError``; texts of any length are stored whole.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import arrowtext as at

BLOCK = 1024
RATE = 8000
PAD = 64
SHIFT = 6  # of the linear predictor's coefficients
PRECISION = 8
LONGEST_CODE = 24  # bits of a Rice code in frames that the vectorised decoder takes
LONGEST_RUN = 15  # zeros of such a code


def _crc_table(poly: int, bits: int, length: int) -> np.ndarray:
    """For every distance from the end and byte: its share of the checksum (shares are joined by XOR)."""
    top, mask = 1 << (bits - 1), (1 << bits) - 1
    one = np.arange(256, dtype=np.uint32) << (bits - 8)
    for _ in range(8):
        one = np.where(one & top, (one << 1) ^ poly, one << 1) & mask
    table = np.zeros((length, 256), np.uint16)
    table[0] = one
    for i in range(1, length):
        before = table[i - 1].astype(np.uint32)
        table[i] = ((before << 8) & mask) ^ one[before >> (bits - 8)]
    return table


_CRC8 = _crc_table(0x07, 8, 20)
_CRC16 = _crc_table(0x8005, 16, 2 * BLOCK + 64)
_ZEROS = np.array([16, *(15 - int(np.log2(i)) for i in range(1, 1 << 16))], np.uint8)  # leading zeros of 16 bits


def checksums(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray, table: np.ndarray) -> np.ndarray:
    """Checksum of every span of at most ``len(table)`` bytes."""
    if not len(starts):
        return np.zeros(0, np.uint16)
    back = np.repeat(np.cumsum(lengths), lengths) - 1 - np.arange(int(lengths.sum()))
    share = table.ravel()[back * 256 + data[at.ragged(starts, lengths)]]
    return np.bitwise_xor.reduceat(share, np.cumsum(lengths) - lengths)


def _number(n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Frame numbers in the format's UTF-8-like form: bytes (7 columns) and their count."""
    size = 1 + sum((n >= lim).astype(np.int64) for lim in (1 << 7, 1 << 11, 1 << 16, 1 << 21, 1 << 26, 1 << 31))
    out = np.zeros((len(n), 7), np.uint8)
    out[:, 0] = n
    for s in range(2, 8):
        of = size == s
        if of.any():
            lead = (0xFF << (8 - s)) & 0xFF
            out[of, 0] = lead | (n[of] >> (6 * (s - 1)))
            for i in range(1, s):
                out[of, i] = 0x80 | ((n[of] >> (6 * (s - 1 - i))) & 0x3F)
    return out, size


def encode(payload: np.ndarray, offs: np.ndarray) -> list[bytes]:
    """A stream for every payload (bytes; each a positive multiple of 64 long)."""
    size = np.diff(offs)
    per = -(-size // BLOCK)
    n_frames = int(per.sum())
    stream = np.repeat(np.arange(len(size)), per)
    number = np.arange(n_frames) - np.repeat(np.cumsum(per) - per, per)
    first = offs[:-1][stream] + number * BLOCK
    length = np.minimum(BLOCK, offs[1:][stream] - first)
    t = np.arange(BLOCK)
    valid = t < length[:, None]
    x = np.zeros((n_frames, BLOCK), np.int32)
    x[valid] = payload[at.ragged(first, length)].astype(np.int32) - 128
    # Residuals of the candidates; the warm-up samples count nothing.
    e1 = np.zeros_like(x)
    e1[:, 1:] = x[:, 1:] - x[:, :-1]
    e2 = np.zeros_like(x)
    e2[:, 2:] = e1[:, 2:] - e1[:, 1:-1]
    f = x.astype(np.float64)
    r0, r1, r2 = (f * f).sum(1), (f[:, 1:] * f[:, :-1]).sum(1), (f[:, 2:] * f[:, :-2]).sum(1)
    det = np.where(r0 * r0 - r1 * r1 > 0, r0 * r0 - r1 * r1, 1)
    limit = (1 << (PRECISION - 1)) - 1
    c1 = np.clip(np.rint(r1 * (r0 - r2) / det * (1 << SHIFT)), -limit, limit).astype(np.int32)
    c2 = np.clip(np.rint((r0 * r2 - r1 * r1) / det * (1 << SHIFT)), -limit, limit).astype(np.int32)
    e3 = np.zeros_like(x)
    e3[:, 2:] = x[:, 2:] - ((c1[:, None] * x[:, 1:-1] + c2[:, None] * x[:, :-2]) >> SHIFT)
    candidates = [x, e1, e2, e3]
    warm_of = np.array([0, 1, 2, 2])
    cost = np.stack([(np.abs(e) * valid).sum(1) for e in candidates], 1)
    kind = cost.argmin(1)
    warm = warm_of[kind]
    e = x.copy()
    for i in range(1, 4):
        e[kind == i] = candidates[i][kind == i]
    coded = valid & (t >= warm[:, None])
    z = (e << 1) ^ (e >> 31)
    n_coded = length - warm
    z *= coded
    # The best parameter is next to the logarithm of the mean.
    near = np.clip(np.log2(np.maximum(z.sum(1) / np.maximum(n_coded, 1), 1)).astype(np.int64), 1, 10)
    tried = near[:, None] + np.array([-1, 0, 1])
    bits = np.stack([(z >> tried[:, i : i + 1].astype(np.int32)).sum(1, dtype=np.int64) + n_coded * (1 + tried[:, i]) for i in range(3)], 1)
    pick = bits.argmin(1)
    k = tried[np.arange(n_frames), pick]
    run = z.max(1) >> k
    # Bits of a subframe: header, warm-up and predictor, Rice header, codes.
    predictor = np.where(kind == 3, 4 + 5 + 2 * PRECISION, 0)
    body = 8 + 8 * warm + predictor + 10 + bits[np.arange(n_frames), pick]
    plain = (body >= 8 + 8 * length) | (run > LONGEST_RUN) | (run + 1 + k > LONGEST_CODE)
    body = np.where(plain, 8 + 8 * length, body)
    digits, n_digits = _number(number)
    head = 4 + n_digits + 2 + 1
    n_bytes = head + -(-body // 8) + 2
    start = np.cumsum(n_bytes) - n_bytes
    out = np.zeros(int(n_bytes.sum()) * 8, np.uint8)
    data = np.zeros(len(out) // 8, np.uint8)

    # Subframes, bit by bit.
    sub = (start + head) * 8
    type_of = np.where(plain, 1, np.where(kind == 3, 0b100001, 0b001000 + kind))
    _put(out, sub + 1, type_of, 6)
    pos = sub + 8
    for i in range(2):
        of = ~plain & (warm > i)
        _put(out, pos[of] + 8 * i, x[of, i] & 0xFF, 8)
    pos = pos + np.where(plain, 0, 8 * warm)
    of = ~plain & (kind == 3)
    for value, width in ((np.full(n_frames, PRECISION - 1), 4), (np.full(n_frames, SHIFT), 5), (c1 & 0xFF, 8), (c2 & 0xFF, 8)):
        _put(out, pos[of], value[of], width)
        pos[of] += width
    of = ~plain
    _put(out, pos[of] + 6, k[of], 4)  # method 0 and partition order 0 before it
    rows, columns = np.nonzero(coded & of[:, None])
    if len(rows):
        zz, kk = z[rows, columns], k.astype(np.int32)[rows]
        q = zz >> kk
        width = q + 1 + kk
        # Where each code begins: running widths, set back to the frame's place.
        run = np.cumsum(width) - width
        begins = np.flatnonzero(np.r_[True, rows[1:] != rows[:-1]])
        where = run - np.repeat(run[begins], np.diff(np.append(begins, len(rows)))) + (pos[rows] + 10)
        stop = where + q
        out[stop] = 1
        for j in range(int(kk.max())):
            use = kk > j
            out[(stop + kk - j)[use]] = (zz[use] >> j) & 1
    data[:] = np.packbits(out)
    del out
    # Verbatim samples are byte-aligned, as are the headers.
    if plain.any():
        data[at.ragged((start + head + 1)[plain], length[plain])] = x[plain][valid[plain]].astype(np.int8).view(np.uint8)
    data[start], data[start + 1], data[start + 2], data[start + 3] = 0xFF, 0xF8, 0x70, 0x02
    for i in range(7):
        of = n_digits > i
        data[(start + 4 + i)[of]] = digits[of, i]
    after = start + 4 + n_digits
    data[after], data[after + 1] = (length - 1) >> 8, (length - 1) & 0xFF
    data[after + 2] = checksums(data, start, head - 1, _CRC8)
    crc = checksums(data, start, n_bytes - 2, _CRC16)
    data[start + n_bytes - 2], data[start + n_bytes - 1] = crc >> 8, crc & 0xFF

    frames = data.tobytes()
    signed = (payload ^ 0x80).tobytes()
    streams = []
    begin = np.cumsum(per) - per
    seek = np.zeros(n_frames, np.dtype([("sample", ">u8"), ("offset", ">u8"), ("count", ">u2")]))
    seek["sample"], seek["offset"], seek["count"] = number * BLOCK, start - start[begin[stream]] if n_frames else start, length
    points = seek.tobytes()
    for i, (a, n) in enumerate(zip(begin.tolist(), per.tolist(), strict=True)):
        b = a + n
        least, most = int(n_bytes[a:b].min()), int(n_bytes[a:b].max())
        total = int(size[i])
        packed = (RATE << 44) | (0 << 41) | (7 << 36) | total
        info = BLOCK.to_bytes(2) * 2 + least.to_bytes(3) + most.to_bytes(3) + packed.to_bytes(8) + hashlib.md5(signed[offs[i] : offs[i + 1]]).digest()
        table = points[18 * a : 18 * b]
        streams.append(b"fLaC\x00" + len(info).to_bytes(3) + info + b"\x83" + len(table).to_bytes(3) + table + frames[int(start[a]) : int(start[b - 1] + n_bytes[b - 1])])
    return streams


def _put(out: np.ndarray, pos: np.ndarray, value: np.ndarray, width: int) -> None:
    for j in range(width):
        out[pos + j] = (value >> (width - 1 - j)) & 1


def _metadata(stream: bytes) -> tuple[int, bytes, np.ndarray, int]:
    """Samples, MD5, seek points and the place of the first frame."""
    if stream[:4] != b"fLaC":
        raise ValueError("not a FLAC stream")
    pos, last, total, md5 = 4, False, 0, b""
    seek = np.zeros(0, np.dtype([("sample", ">u8"), ("offset", ">u8"), ("count", ">u2")]))
    while not last:
        last, kind, n = bool(stream[pos] & 0x80), stream[pos] & 0x7F, int.from_bytes(stream[pos + 1 : pos + 4])
        body = stream[pos + 4 : pos + 4 + n]
        if kind == 0:
            packed = int.from_bytes(body[10:18])
            if (packed >> 41) & 7 or ((packed >> 36) & 31) != 7:
                raise ValueError("only 8-bit mono is read")
            total, md5 = packed & ((1 << 36) - 1), body[18:34]
        elif kind == 3:
            seek = np.frombuffer(body, seek.dtype)
        pos += 4 + n
    return total, md5, seek, pos


def decode(streams: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Samples of all streams as one int8 array, their offsets, and the first sample of every block (frame)."""
    metas = [_metadata(s) for s in streams]
    data = np.frombuffer(b"".join(s[m[3] :] for s, m in zip(streams, metas, strict=True)) + bytes(8), np.uint8)
    body = np.array([len(s) - m[3] for s, m in zip(streams, metas, strict=True)], np.int64)
    base = np.cumsum(body) - body
    totals = np.array([m[0] for m in metas], np.int64)
    offs = np.concatenate([[0], np.cumsum(totals)])
    per = np.array([len(m[2]) for m in metas], np.int64)
    points = np.concatenate([m[2] for m in metas]) if metas else np.zeros(0)
    if not len(points):
        return np.zeros(0, np.int8), offs, np.zeros(0, np.int64)
    stream = np.repeat(np.arange(len(streams)), per)
    start = base[stream] + points["offset"].astype(np.int64)
    first = offs[stream] + points["sample"].astype(np.int64)
    end = np.append(start[1:], base[-1] + body[-1])
    n = len(start)
    if (data[start] != 0xFF).any() or (data[start + 1] != 0xF8).any():
        raise ValueError("no sync code where the seek table points to")
    lead = data[start + 4]
    n_digits = np.where(lead < 0x80, 1, _ZEROS[(~lead).astype(np.uint16) << 8])
    code = data[start + 2] >> 4
    extra = np.where(code == 6, 1, np.where(code == 7, 2, 0))
    after = start + 4 + n_digits
    length = np.where(code == 7, data[after].astype(np.int64) * 256 + data[after + 1] + 1, np.where(code == 6, data[after].astype(np.int64) + 1, np.where(code >= 8, np.int64(256) << np.maximum(code.astype(np.int64) - 8, 0), np.int64(576) << np.maximum(code.astype(np.int64) - 2, 0))))
    head = 4 + n_digits + extra + 1
    if (checksums(data, start, head - 1, _CRC8) != data[start + head - 1]).any():
        raise ValueError("a frame header fails its checksum")
    n_bytes = end - start
    short = n_bytes <= len(_CRC16)
    crc = np.zeros(n, np.uint16)
    crc[short] = checksums(data, start[short], n_bytes[short] - 2, _CRC16)
    for i in np.flatnonzero(~short):
        crc[i] = _crc16(data[start[i] : end[i] - 2].tobytes())
    if (crc != data[end - 2].astype(np.uint16) * 256 + data[end - 1]).any():
        raise ValueError("a frame fails its checksum")

    x = np.zeros((n, int(length.max())), np.int32)
    sub = start + head
    kind = data[sub].astype(np.int64)
    at_bits = (sub + 1) * 8
    plain = kind == 0b10
    for i in np.flatnonzero(plain):
        x[i, : length[i]] = data[sub[i] + 1 : sub[i] + 1 + length[i]].view(np.int8)
    fixed, linear = (kind >= 0b0010000) & (kind <= 0b0011000) & (kind % 2 == 0), (kind >= 0b1000000) & (kind % 2 == 0)
    order = np.where(fixed, (kind >> 1) - 8, np.where(linear, (kind >> 1) - 31, 0))
    rice = (fixed & (order <= 4)) | (linear & (order <= 4))
    lanes = np.flatnonzero(rice)
    slow = ~plain & ~rice
    if len(lanes):
        big = data.astype(np.uint32)
        window = np.zeros(len(data), np.uint32)
        window[:-3] = (big[:-3] << 24) | (big[1:-2] << 16) | (big[2:-1] << 8) | big[3:]
        pos = at_bits[lanes].copy()

        def take(width, of=slice(None)):
            p = pos[of]
            got = (window[p >> 3] << (p & 7).astype(np.uint32)) >> np.uint32(32 - width)
            pos[of] += width
            return got.astype(np.int64)

        o, lin = order[lanes], linear[lanes]
        for i in range(4):
            of = np.flatnonzero(o > i)
            x[lanes[of], i] = (take(8, of) ^ 0x80) - 0x80
        coefs, shift = np.zeros((len(lanes), 4), np.int64), np.zeros(len(lanes), np.int64)
        of = np.flatnonzero(lin)
        if len(of):
            width, shift[of] = take(4, of) + 1, take(5, of)
            for w in np.unique(width):
                for i in range(4):
                    has = of[(width == w) & (o[of] > i)]
                    v = take(int(w), has)
                    coefs[has, i] = v - ((v >> (w - 1)) << w)
        method, parts, k = take(2), take(4), take(4)
        odd = (method != 0) | (parts != 0) | (k == 15)
        slow[lanes[odd]] = True
        lanes, o, lin, coefs, shift, k, pos = lanes[~odd], o[~odd], lin[~odd], coefs[~odd], shift[~odd], k[~odd], pos[~odd]
        by = np.argsort(-(length[lanes] - o), kind="stable")
        todo = (length[lanes] - o)[by]
        pos, kk, low = pos[by], k[by].astype(np.uint32), (32 - k[by]).astype(np.uint32)
        res = np.zeros((int(todo[0]) if len(todo) else 0, len(lanes)), np.int32)
        active, too_long = len(lanes), np.zeros(len(lanes), bool)
        for step in range(len(res)):
            while active and todo[active - 1] <= step:
                active -= 1
            p = pos[:active]
            w = window[p >> 3] << (p & 7).astype(np.uint32)
            q = _ZEROS[w >> 16].astype(np.uint32)
            rest = np.where(kk[:active] > 0, (w << (q + 1)) >> (low[:active] & 31), 0)
            z = ((q << kk[:active]) | rest).astype(np.int32)
            res[step, :active] = (z >> 1) ^ -(z & 1)
            used = q + 1 + kk[:active]
            too_long[:active] |= (used > LONGEST_CODE) | (q > LONGEST_RUN)
            pos[:active] = p + used
        slow[lanes[by[too_long]]] = True
        back = np.empty_like(by)
        back[by] = np.arange(len(by))
        res = res[:, back].T
        for warm in np.unique(o):
            of = np.flatnonzero((o == warm) & ~lin)
            if len(of):
                m = min(res.shape[1], x.shape[1] - warm)
                x[lanes[of], warm : warm + m] = res[of, :m]
                _integrate(x, lanes[of], int(warm))
        of = np.flatnonzero(lin)
        if len(of):
            y, c, s = np.ascontiguousarray(x[lanes[of]].T).astype(np.int64), coefs[of], shift[of]
            for warm in np.unique(o[of]):
                g = np.flatnonzero(o[of] == warm)
                part, r, cc, ss = np.ascontiguousarray(y[:, g]), np.ascontiguousarray(res[of[g]].T), cc_of(c[g], warm), s[g]
                for i in range(int(warm), int((length[lanes[of[g]]]).max())):
                    total = cc[0] * part[i - 1]
                    for j in range(1, warm):
                        total += cc[j] * part[i - 1 - j]
                    part[i] = r[i - warm] + (total >> ss)
                x[lanes[of[g]]] = part.T
    for i in np.flatnonzero(slow):
        x[i, : length[i]] = scalar_subframe(data[sub[i] : end[i] - 2].tobytes(), int(length[i]))
    out = np.zeros(int(offs[-1]), np.int8)
    valid = np.arange(x.shape[1]) < length[:, None]
    out[at.ragged(first, length)] = x[valid]
    for i, m in enumerate(metas):
        if hashlib.md5(out[offs[i] : offs[i + 1]].tobytes()).digest() != m[1]:
            raise ValueError("a stream fails its MD5")
    return out, offs, first


def cc_of(c: np.ndarray, warm: int) -> list[np.ndarray]:
    return [np.ascontiguousarray(c[:, j]) for j in range(warm)]


def _integrate(x: np.ndarray, rows: np.ndarray, order: int) -> None:
    """Undo differences of the order, whose first ``order`` columns hold samples."""
    y = x[rows].astype(np.int64)
    starts = [y[:, :order]]
    for _ in range(order - 1):
        starts.append(np.diff(starts[-1], axis=1))
    for level in range(order - 1, -1, -1):
        # Column order-1 becomes the last known difference of this level, then sums run on.
        y[:, order - 1] = starts[level][:, -1]
        y[:, order - 1 :] = np.cumsum(y[:, order - 1 :], axis=1)
    if order:
        y[:, :order] = starts[0]
    x[rows] = y


def _crc16(data: bytes) -> int:
    crc = 0
    for b in data:
        crc = ((crc << 8) & 0xFFFF) ^ int(_CRC16[0][(crc >> 8) ^ b])
    return crc


def scalar_subframe(data: bytes, n: int) -> list[int]:
    """One 8-bit subframe in any form, sample by sample."""
    value, left = int.from_bytes(data), len(data) * 8

    def take(width: int) -> int:
        nonlocal left
        left -= width
        return (value >> left) & ((1 << width) - 1)

    def signed(width: int) -> int:
        v = take(width)
        return v - ((v >> (width - 1)) << width) if width else 0

    def unary() -> int:
        zeros = 0
        while not take(1):
            zeros += 1
        return zeros

    take(1)
    kind, wasted = take(6), 0
    if take(1):
        wasted = unary() + 1
    width = 8 - wasted
    if kind == 0:
        out = [signed(width)] * n
    elif kind == 1:
        out = [signed(width) for _ in range(n)]
    else:
        linear = kind >= 32
        order = kind - 31 if linear else kind - 8
        out = [signed(width) for _ in range(order)]
        if linear:
            precision = take(4) + 1
            shift = signed(5)
            coefs = [signed(precision) for _ in range(order)]
        else:
            shift, coefs = 0, [[], [1], [2, -1], [3, -3, 1], [4, -6, 4, -1]][order]
        long, parts = take(2), take(4)
        for part in range(1 << parts):
            k, escape = (take(5), 31) if long else (take(4), 15)
            raw = take(5) if k == escape else None
            for _ in range((n >> parts) - (order if part == 0 else 0)):
                if raw is not None:
                    e = signed(raw)
                else:
                    z = unary()
                    z = z << k | take(k)
                    e = (z >> 1) ^ -(z & 1)
                out.append(e + (sum(c * out[-1 - i] for i, c in enumerate(coefs)) >> shift))
    return [v << wasted for v in out]


def payloads(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """UTF-8 bytes of every text, padded; their offsets and the lengths without padding."""
    data, offs = at.string_buffers(column)
    size = np.diff(offs)
    padded = np.maximum(PAD, -(-size // PAD) * PAD)
    out_offs = np.concatenate([[0], np.cumsum(padded)])
    out = np.zeros(int(out_offs[-1]), np.uint8)
    out[at.ragged(out_offs[:-1], size)] = data
    return out, out_offs, size


def features(samples: np.ndarray) -> str:
    """Sample count, mean, mean square, zero crossings and mean absolute step, as whole thousandths."""
    x = samples.astype(np.int64)
    n = len(x)
    return f"n={n};mean={int(x.sum()) * 1000 // n};power={int((x * x).sum()) * 1000 // n};cross={int(((x[1:] < 0) != (x[:-1] < 0)).sum())};step={int(np.abs(np.diff(x)).sum()) * 1000 // n}"


def media(docs: DataFrame, key: str = "doc_id", text: str = "text", with_media: bool = False) -> DataFrame:
    """Stores every text as a FLAC stream, reads it back, and gives digests and features; with_media adds the stream."""
    source = docs.select(F.col(key).alias("doc_id"), F.col(text).alias("t"))
    fields = f"doc_id {source.schema['doc_id'].dataType.simpleString()}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string" + ", media binary" * with_media

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in at.blocks(batch, "t", 1 << 20):
                payload, offs, size = payloads(part.column("t"))
                streams = encode(payload, offs)
                samples, back, _ = decode(streams)
                rows = []
                for i, stream in enumerate(streams):
                    own = samples[back[i] : back[i + 1]]
                    raw = (own.view(np.uint8) ^ 0x80).tobytes()
                    row = (int(size[i]), len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-PAD:]), len(stream), hashlib.sha256(stream).hexdigest(), features(own))
                    rows.append(row + (stream,) * with_media)
                types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary()]
                names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "media"]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *(pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=False))], names=names[: 8 + with_media])

    return source.mapInArrow(run, fields)


def pcm_blocks(streams: DataFrame, key: str = "doc_id", media_: str = "media") -> DataFrame:
    """doc_id, block, first_sample, n_samples and pcm (unsigned 8-bit) for every frame of the streams."""
    source = streams.select(F.col(key).alias("doc_id"), F.col(media_).alias("m")).where("m is not null")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at_row in range(0, batch.num_rows, 64):
                part = batch.slice(at_row, 64)
                samples, offs, first = decode(part.column("m").to_pylist())
                owner = np.searchsorted(offs, first, "right") - 1
                end = np.append(first[1:], offs[-1])
                starts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
                block = np.arange(len(first)) - np.repeat(starts, np.diff(np.append(starts, len(first))))
                pcm = [(samples[a:b].view(np.uint8) ^ 0x80).tobytes() for a, b in zip(first, end, strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(owner)), pa.array(block), pa.array(first - offs[owner]), pa.array(end - first), pa.array(pcm, pa.binary())], names=["doc_id", "block", "first_sample", "n_samples", "pcm"])

    return source.mapInArrow(run, f"doc_id {source.schema['doc_id'].dataType.simpleString()}, block long, first_sample long, n_samples long, pcm binary")
