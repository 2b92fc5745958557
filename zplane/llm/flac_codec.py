"""A FLAC codec in numpy that works on many frames at once.

The encoder writes mono streams (STREAMINFO with MD5, a SEEKTABLE with a point for every frame, then
frames with constant, verbatim, fixed-predictor or linear-predictor subframes and Rice-coded
residuals). The decoder reads mono streams of 4 to 16 bits with any of these subframes, any partition
order, both Rice methods and escaped partitions, and checks the header CRC-8, the frame CRC-16 and the
MD5 of the samples. Residuals of all frames of a group are decoded in step: the i-th code of every
frame is found by one round of array operations on 64-bit windows of the stream.
"""

from __future__ import annotations

import hashlib

import numpy as np

BLOCK = 4096
_U = np.uint64


class FlacError(ValueError):
    """A stream that breaks the format or fails a checksum."""


def _crc_table(poly: int, bits: int) -> list[int]:
    out, top, mask = [], 1 << (bits - 1), (1 << bits) - 1
    for n in range(256):
        c = n << (bits - 8)
        for _ in range(8):
            c = ((c << 1) ^ poly if c & top else c << 1) & mask
        out.append(c)
    return out


_CRC8 = _crc_table(0x07, 8)
_CRC16 = np.array(_crc_table(0x8005, 16), np.uint16)


def crc8(data: bytes) -> int:
    c = 0
    for x in data:
        c = _CRC8[c ^ x]
    return c


class _Crc16:
    """CRC-16 of many byte ranges: it is linear, so a byte adds a value that depends on its distance to the end."""

    def __init__(self):
        self.by_distance = _CRC16[None, :].copy()

    def __call__(self, buf: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        n = end - start
        need = int(n.max(initial=1))
        if need > len(self.by_distance):
            rows = list(self.by_distance)
            while len(rows) < need:
                rows.append((rows[-1] << np.uint16(8)) ^ _CRC16[rows[-1] >> np.uint16(8)])
            self.by_distance = np.stack(rows)
        first = np.cumsum(n) - n
        inside = np.arange(int(n.sum())) - np.repeat(first, n)
        far = np.repeat(n, n) - 1 - inside
        part = self.by_distance[far, buf[np.repeat(start, n) + inside]]
        return np.bitwise_xor.reduceat(part, first)


crc16 = _Crc16()


def _utf8_number(n: int) -> bytes:
    """The extended UTF-8 form of a frame or sample number (up to 36 bits)."""
    if n < 0x80:
        return bytes([n])
    tail = []
    room = 0x3F
    while n > room:
        tail.append(0x80 | (n & 0x3F))
        n >>= 6
        room >>= 1
    return bytes([((~room << 1) & 0xFF) | n, *reversed(tail)])


def _frame_header(number: int, n: int) -> bytes:
    code = 12 if n == 4096 else 7
    head = bytes([0xFF, 0xF8, code << 4, 0b0000_001_0]) + _utf8_number(number)
    if code == 7:
        head += (n - 1).to_bytes(2, "big")
    return head + bytes([crc8(head)])


def _lpc(x: np.ndarray, order: int, precision: int = 12) -> tuple[list[int], int] | None:
    """Quantised linear-prediction coefficients of one frame, or None if it has no usable ones."""
    f = x.astype(np.float64)
    r = [float(f[i:] @ f[: len(f) - i]) for i in range(order + 1)]
    if r[0] <= 0 or len(f) <= order:
        return None
    a, err = [], r[0]
    for i in range(order):
        k = (r[i + 1] - sum(c * r[i - j] for j, c in enumerate(a))) / err
        a = [c - k * d for c, d in zip(a, reversed(a))] + [k]
        err *= 1 - k * k
        if err <= 0:
            return None
    top = max(map(abs, a))
    if not top:
        return None
    shift = min(15, max(0, precision - 2 - int(np.floor(np.log2(top)))))
    lim = 1 << (precision - 1)
    return [max(-lim, min(lim - 1, round(c * (1 << shift)))) for c in a], shift


def encode(payloads: list[bytes], lpc_order: int = 0) -> list[bytes]:
    """Mono 8-bit streams of the payloads (bytes as unsigned samples). Empty payloads give streams without frames."""
    sizes = np.array([len(p) for p in payloads], np.int64)
    if not sizes.sum():
        return [_stream_head(b"", 0, [], []) for _ in payloads]
    x = np.frombuffer(b"".join(payloads), np.uint8).astype(np.int32) - 128
    of, starts, lens = [], [], []
    at = 0
    for d, size in enumerate(sizes.tolist()):
        for s in range(0, size, BLOCK):
            of.append(d)
            starts.append(at + s)
            lens.append(min(BLOCK, size - s))
        at += size
    start, n = np.array(starts, np.int64), np.array(lens, np.int64)
    frames = len(n)
    inside = np.arange(len(x)) - np.repeat(start, n)

    # residuals of the fixed predictors of order 0, 1 and 2; the cheapest by sum of magnitudes
    res = [x]
    for order in (1, 2):
        d = np.zeros_like(x)
        d[1:] = res[-1][1:] - res[-1][:-1]
        d[inside < order] = 0
        res.append(d)
    cost = np.stack([np.add.reduceat(np.abs(r).astype(np.int64), start) for r in res])
    cost[1][n < 2] = cost[2][n < 3] = np.iinfo(np.int64).max
    kind = np.argmin(cost, axis=0)
    constant = (np.maximum.reduceat(x, start) == np.minimum.reduceat(x, start))
    r = np.choose(np.repeat(kind, n), res)
    order = kind.copy()
    lpc: dict[int, tuple[list[int], int]] = {}
    if lpc_order:
        for f in range(frames):
            got = None if constant[f] else _lpc(x[start[f] : start[f] + n[f]], lpc_order)
            if got:
                lpc[f] = got
                seg = x[start[f] : start[f] + n[f]].astype(np.int64)
                pred = sum(c * seg[lpc_order - 1 - j : len(seg) - 1 - j] for j, c in enumerate(got[0])) >> got[1]
                r[start[f] + lpc_order : start[f] + n[f]] = seg[lpc_order:] - pred
                r[start[f] : start[f] + lpc_order] = 0
                order[f] = lpc_order
    u = np.where(r < 0, -2 * r - 1, 2 * r)
    mean = np.add.reduceat(u.astype(np.int64), start) / np.maximum(1, n - order)
    k = np.clip(np.floor(np.log2(np.maximum(mean, 1e-9) * 0.6931) + 0.5), 0, 14).astype(np.int64)
    warm = inside < np.repeat(order, n)
    q = u >> np.repeat(k, n)
    q[warm] = 0
    bits = np.add.reduceat(q.astype(np.int64), start) + (n - order) * (k + 1) + 8 * order + 18
    verbatim = ~constant & (bits > 8 * n + 8) & ~np.isin(np.arange(frames), list(lpc))
    plain = constant | verbatim

    # one entry for each field of the subframes: zero bits before it, value, width
    per_frame = np.repeat(plain, n)
    widths = np.where(per_frame | warm, 8, np.repeat(k, n) + 1)
    values = np.where(per_frame | warm, x & 0xFF, (1 << np.repeat(k, n)) | (u & ((1 << np.repeat(k, n)) - 1)))
    gaps = np.where(per_frame | warm, 0, q)
    dropped = np.repeat(constant, n) & (inside > 0)
    widths[dropped] = 0
    values[dropped] = 0
    head_at = start + 2 * np.arange(frames)
    entry = np.arange(len(x)) + 2 * np.repeat(np.arange(frames), n)
    entry += np.where(warm & ~per_frame, 1, 2)
    total = len(x) + 2 * frames
    width, value, gap = np.zeros(total, np.int64), np.zeros(total, np.int64), np.zeros(total, np.int64)
    width[entry], value[entry], gap[entry] = widths, values, gaps
    width[head_at] = 8
    value[head_at] = np.where(constant, 0x00, np.where(verbatim, 0x02, (8 | order) << 1))
    rice = head_at + 1 + np.where(plain, 0, order)
    width[rice] = np.where(plain, 0, 10)
    value[rice] = np.where(plain, 0, k)
    heads, extra = [], np.zeros(frames, np.int64)
    count: dict[int, int] = {}
    for f, d in enumerate(of):
        heads.append(_frame_header(count.get(d, 0), int(n[f])))
        count[d] = count.get(d, 0) + 1
    for f, (c, shift) in lpc.items():  # precision, shift and coefficients come between warm-up and residual
        v = 12 - 1 << 5 | shift
        for a in c:
            v = v << 12 | (a & 0xFFF)
        extra[f] = 9 + 12 * len(c)
        value[head_at[f]] = (32 | (len(c) - 1)) << 1
        lpc[f] = (v, int(extra[f]))
    gap[rice] += extra
    span = gap + width
    ends = np.cumsum(span)
    before = ends[head_at] - span[head_at]
    frame_bits = np.append(before[1:], ends[-1]) - before
    head_len = np.array([len(h) for h in heads], np.int64)
    frame_len = head_len + (frame_bits + 7) // 8 + 2
    frame_at = np.cumsum(frame_len) - frame_len
    frame_of = np.repeat(np.arange(frames), n + 2)
    pos = ends - width + (8 * (frame_at + head_len) - before)[frame_of]
    out = np.zeros(int(frame_len.sum()) + 8, np.uint8)
    v = value.astype(np.uint64) << (32 - width - (pos & 7)).astype(np.uint64)
    at = pos >> 3
    first = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
    word = np.add.reduceat(v, first)
    at = at[first]
    for j in range(4):
        out[at + j] |= ((word >> _U(24 - 8 * j)) & _U(255)).astype(np.uint8)
    for f, h in enumerate(heads):
        out[frame_at[f] : frame_at[f] + len(h)] = np.frombuffer(h, np.uint8)
    for f, (v, size) in lpc.items():
        _put_bits(out, int(8 * (frame_at[f] + head_len[f]) + 8 + 8 * order[f]), v, size)
    end = frame_at + frame_len - 2
    c = crc16(out, frame_at, end)
    out[end], out[end + 1] = (c >> 8).astype(np.uint8), (c & 0xFF).astype(np.uint8)
    body = out.tobytes()

    result, f = [], 0
    for d, p in enumerate(payloads):
        m = count.get(d, 0)
        lo = int(frame_at[f]) if m else 0
        hi = int(frame_at[f + m - 1] + frame_len[f + m - 1]) if m else 0
        result.append(_stream_head(p, BLOCK, n[f : f + m].tolist(), frame_len[f : f + m].tolist()) + body[lo:hi])
        f += m
    return result


def _put_bits(out: np.ndarray, pos: int, v: int, size: int) -> None:
    lo, hi = pos >> 3, (pos + size + 7) >> 3
    old = int.from_bytes(out[lo:hi].tobytes(), "big")
    new = old | v << (8 * (hi - lo) - (pos & 7) - size)
    out[lo:hi] = np.frombuffer(new.to_bytes(hi - lo, "big"), np.uint8)


def _stream_head(payload: bytes, block: int, sizes: list[int], lengths: list[int]) -> bytes:
    signed = (np.frombuffer(payload, np.uint8) ^ 0x80).tobytes()
    lo, hi = (min(lengths), max(lengths)) if lengths else (0, 0)
    info = (16).to_bytes(2, "big") if not block else block.to_bytes(2, "big")
    info = info * 2 + lo.to_bytes(3, "big") + hi.to_bytes(3, "big")
    info += (44100 << 44 | 0 << 41 | 7 << 36 | len(payload)).to_bytes(8, "big") + hashlib.md5(signed).digest()
    points, at, offset = [], 0, 0
    for n, size in zip(sizes, lengths):
        points.append(at.to_bytes(8, "big") + offset.to_bytes(8, "big") + n.to_bytes(2, "big"))
        at += n
        offset += size
    table = b"".join(points)
    head = b"fLaC" + bytes([0x00 if points else 0x80]) + len(info).to_bytes(3, "big") + info
    return head + (bytes([0x83]) + len(table).to_bytes(3, "big") + table if points else b"")


class _Bits:
    """Reads bit fields of one stream."""

    def __init__(self, data: bytes, pos: int):
        self.data, self.pos = data, pos

    def take(self, n: int) -> int:
        lo, hi = self.pos >> 3, (self.pos + n + 7) >> 3
        if hi > len(self.data):
            raise FlacError("the stream ends inside a frame")
        v = int.from_bytes(self.data[lo:hi], "big") >> (8 * (hi - lo) - (self.pos & 7) - n)
        self.pos += n
        return v & ((1 << n) - 1)

    def signed(self, n: int) -> int:
        v = self.take(n)
        return v - (1 << n) if n and v >> (n - 1) else v


class _Frame:
    __slots__ = ("bits", "coef", "end", "first", "n", "number", "order", "p", "method", "parts", "samples", "shift", "start", "stream", "wasted")


def _metadata(data: bytes) -> dict:
    if data[:4] != b"fLaC":
        raise FlacError("not a FLAC stream")
    at, info, points, last = 4, None, None, False
    while not last:
        if at + 4 > len(data):
            raise FlacError("the metadata is cut off")
        last, kind, size = bool(data[at] & 0x80), data[at] & 0x7F, int.from_bytes(data[at + 1 : at + 4], "big")
        block = data[at + 4 : at + 4 + size]
        if kind == 0:
            v = int.from_bytes(block[10:18], "big")
            info = {"block": int.from_bytes(block[2:4], "big"), "rate": v >> 44, "channels": (v >> 41 & 7) + 1, "bits": (v >> 36 & 31) + 1, "total": v & ((1 << 36) - 1), "md5": block[18:34]}
        elif kind == 3:
            points = [tuple(int.from_bytes(block[i + a : i + b], "big") for a, b in ((0, 8), (8, 16), (16, 18))) for i in range(0, size, 18)]
        at += 4 + size
    if info is None:
        raise FlacError("no STREAMINFO")
    if info["channels"] != 1 or not 4 <= info["bits"] <= 16:
        raise FlacError("only mono streams of 4 to 16 bits are read")
    return info | {"at": at, "points": [p for p in points or () if p[0] != (1 << 64) - 1]}


_SIZES = {1: 192, **{c: 576 << (c - 2) for c in range(2, 6)}, **{c: 256 << (c - 8) for c in range(8, 16)}}
_DEPTHS = {1: 8, 2: 12, 4: 16}


def _open_frame(data: bytes, at: int, info: dict) -> _Frame:
    """Parse a frame up to its first Rice code."""
    if len(data) < at + 6 or data[at] != 0xFF or data[at + 1] & 0xFE != 0xF8:
        raise FlacError("no frame sync code")
    b = _Bits(data, 8 * at + 16)
    size_code, rate_code, channels, depth_code, _ = b.take(4), b.take(4), b.take(4), b.take(3), b.take(1)
    lead = b.take(8)
    more = 0 if lead < 0x80 else 8 - (~lead & 0xFF).bit_length() - 1
    number = lead if lead < 0x80 else lead & ((1 << (6 - more)) - 1)
    for _ in range(more):
        number = number << 6 | (b.take(8) & 0x3F)
    n = b.take(8) + 1 if size_code == 6 else b.take(16) + 1 if size_code == 7 else _SIZES.get(size_code)
    if rate_code in (12, 13, 14):
        b.take(8 if rate_code == 12 else 16)
    if n is None or channels:
        raise FlacError("a frame with a reserved size or several channels")
    if b.take(8) != crc8(data[at : (b.pos >> 3) - 1]):
        raise FlacError("frame header CRC-8 differs")
    f = _Frame()
    f.start, f.n, f.coef, f.shift, f.parts, f.samples, f.order, f.number = at, n, None, 0, 0, None, 0, number
    f.bits = _DEPTHS.get(depth_code, info["bits"])
    b.take(1)
    kind, f.wasted = b.take(6), 0
    if b.take(1):
        f.wasted = 1
        while not b.take(1):
            f.wasted += 1
    width = f.bits - f.wasted
    if kind == 0:
        f.samples = np.full(n, b.signed(width), np.int64)
    elif kind == 1:
        if width == 8 and not b.pos & 7:
            raw = np.frombuffer(data, np.int8, n, b.pos >> 3) if len(data) >= (b.pos >> 3) + n else b.take(1 << 40)
            f.samples = raw.astype(np.int64)
            b.pos += 8 * n
        else:
            f.samples = np.array([b.signed(width) for _ in range(n)], np.int64)
    elif 8 <= kind <= 12 or kind >= 32:
        f.order = kind - 8 if kind < 32 else kind - 31
        if f.order > n:
            raise FlacError("more warm-up samples than samples")
        f.first = [b.signed(width) for _ in range(f.order)]
        if kind >= 32:
            precision = b.take(4) + 1
            f.shift = b.signed(5)
            f.coef = [b.signed(precision) for _ in range(f.order)]
        f.method = b.take(2)
        f.parts = b.take(4)
        if f.method > 1 or n >> f.parts << f.parts != n or (n >> f.parts) < f.order:
            raise FlacError("a reserved or impossible residual coding")
    else:
        raise FlacError("a reserved subframe type")
    f.p = b.pos
    return f


def _residuals(frames: list[_Frame], buf: np.ndarray, base: np.ndarray) -> list[np.ndarray]:
    """The Rice residuals of many frames, decoded in step; sets f.p to the bit after each frame's subframe."""
    by_size = sorted(range(len(frames)), key=lambda i: frames[i].order - frames[i].n)
    fs = [frames[i] for i in by_size]
    left = np.array([f.n - f.order for f in fs], np.int64)
    p = np.array([f.p for f in fs], np.int64) + 8 * base[by_size]
    w = np.zeros(len(buf), np.uint64)
    for j in range(8):
        w[: len(buf) - 8] |= buf[j : len(buf) - 8 + j].astype(np.uint64) << _U(56 - 8 * j)
    last = len(buf) - 9
    k = np.zeros(len(fs), np.uint64)
    raw = np.full(len(fs), -1, np.int64)
    switch: dict[int, list[int]] = {}
    for i, f in enumerate(fs):
        for j in range(1 << f.parts):
            at = max(0, (f.n >> f.parts) * j - f.order)
            if j == 0 or (f.n >> f.parts) * j - f.order >= 0:
                switch.setdefault(at, []).append(i)
    steps = int(left.max(initial=0))
    out = np.zeros((steps, len(fs)), np.int32)
    live = np.searchsorted(-left, -np.arange(steps), side="left")  # frames with more than i residuals
    five = np.array([f.method for f in fs], bool)
    some_raw = False
    one, eleven, seven = _U(1), _U(11), np.int64(7)

    def field(rows: np.ndarray, width: np.ndarray) -> np.ndarray:
        at = np.minimum(p[rows] >> 3, last)
        v = (w[at] << (p[rows] & seven).astype(np.uint64)) >> one >> (63 - width).astype(np.uint64)
        p[rows] += width
        return v.astype(np.int64)

    for i in range(max(steps, 1)):
        for rows in (np.array(switch[i], np.int64),) if i in switch else ():
            width = np.where(five[rows], 5, 4)
            got = field(rows, width)
            escape = got == (1 << width) - 1
            raw[rows] = -1
            if escape.any():
                raw[rows[escape]] = field(rows[escape], np.full(int(escape.sum()), 5))
            some_raw = bool((raw >= 0).any())
            k[rows] = np.where(escape, 0, got).astype(np.uint64)
        if i >= steps:
            break
        m = int(live[i])
        pm, km = p[:m], k[:m]
        x = w[np.minimum(pm >> 3, last)] << (pm & seven).astype(np.uint64)
        zeros = 53 - np.frexp((x >> eleven).astype(np.float64))[1].astype(np.int64)
        far = np.flatnonzero((zeros >= 53) | (zeros + 1 + km.astype(np.int64) > 56))  # 53: no one bit in sight
        z = zeros.astype(np.uint64)
        u = (z << km) | ((x << (z + one)) >> one >> (_U(63) - km))
        step = zeros + 1 + km.astype(np.int64)
        for j in far.tolist():  # long runs of zeros, or a large parameter after them
            if raw[j] < 0:
                start = at = int(pm[j])
                while at >> 3 < last and not buf[at >> 3] >> (7 - (at & 7)) & 1:
                    at += 1
                if at >> 3 >= last:
                    raise FlacError("the stream ends inside a residual")
                kj, v = int(km[j]), 0
                for b in range(at + 1, at + 1 + kj):
                    v = v << 1 | int(buf[min(b >> 3, last)] >> (7 - (b & 7)) & 1)
                u[j] = (at - start) << kj | v
                step[j] = at - start + 1 + kj
        r = (u >> one).astype(np.int64) ^ -(u & one).astype(np.int64)
        if some_raw:
            rows = np.flatnonzero(raw[:m] >= 0)
            width = raw[rows]
            v = (x[rows] >> one >> (63 - width).astype(np.uint64)).astype(np.int64)
            r[rows] = np.where(width > 0, v - ((v >> np.maximum(width - 1, 0) & 1) << width), 0)
            step[rows] = width
        out[i, :m] = r
        p[:m] += step
    flat = np.ascontiguousarray(out.T)
    result: list = [None] * len(fs)
    for i, j in enumerate(by_size):
        result[j] = flat[i, : left[i]].astype(np.int64)
        fs[i].p = int(p[i]) - 8 * int(base[j])
    return result


def _restore(f: _Frame, r: np.ndarray | None) -> np.ndarray:
    if f.samples is None:
        if f.coef is None:
            x = r
            warm = np.array(f.first, np.int64)
            for level in range(f.order, 0, -1):
                x = np.cumsum(np.append(np.diff(warm, level - 1)[-1:], x))[1:]
            f.samples = np.append(warm, x)
        else:
            x = list(f.first)
            order, coef = f.order, f.coef[::-1]
            for v in r.tolist():
                x.append(v + (sum(a * b for a, b in zip(coef, x[-order:])) >> f.shift))
            f.samples = np.array(x, np.int64)
    return f.samples << f.wasted


def decode(streams: list[bytes | None]) -> list[dict]:
    """For each stream: {"samples", "info", "blocks": [(first sample, samples, byte offset)]} or {"error": why}."""
    result: list[dict] = [{} for _ in streams]
    waiting: list[tuple[int, int]] = []
    for s, data in enumerate(streams):
        try:
            if data is None:
                raise FlacError("no stream")
            info = _metadata(data)
            result[s] = {"info": info, "frames": []}
            if info["points"] and sum(p[2] for p in info["points"]) == info["total"]:
                waiting += [(s, info["at"] + p[1]) for p in info["points"]]
                info["seek"] = True
            elif info["total"] or len(data) > info["at"]:
                waiting.append((s, info["at"]))
        except FlacError as e:
            result[s] = {"error": str(e)}
    while waiting:  # with a seek table one round reads all frames, else each round reads one of every stream
        todo, waiting, opened = waiting, [], []
        for s, at in todo:
            try:
                f = _open_frame(streams[s], at, result[s]["info"])
                f.stream = s
                opened.append(f)
            except (FlacError, KeyError) as e:
                result[s] = {"error": str(e)}
        coded = [f for f in opened if f.samples is None]
        used = sorted({f.stream for f in opened})
        place, at = {}, 0
        for s in used:
            place[s] = at
            at += len(streams[s])
        buf = np.frombuffer(b"".join([*(streams[s] for s in used), bytes(16)]), np.uint8)
        if coded:
            try:
                found = _residuals(coded, buf, np.array([place[f.stream] for f in coded], np.int64))
            except FlacError as e:
                if len(used) == 1:
                    result[used[0]] = {"error": str(e)}
                    continue
                for s in used:  # one stream is broken: read each alone
                    result[s] = decode([streams[s]])[0]
                continue
        else:
            found = []
        for f, r in zip(coded, found):
            _restore(f, r)
        ends = np.array([((f.p + 7) >> 3) for f in opened], np.int64)
        for f, e in zip(opened, ends.tolist()):
            if e + 2 > len(streams[f.stream]):
                result[f.stream] = {"error": "the stream ends inside a frame"}
        kept = [i for i, f in enumerate(opened) if "error" not in result[f.stream]]
        if kept:
            start = np.array([place[opened[i].stream] + opened[i].start for i in kept], np.int64)
            end = np.array([place[opened[i].stream] for i in kept], np.int64) + ends[kept]
            want = buf[end].astype(np.uint16) << 8 | buf[end + 1]
            for i, same in zip(kept, (crc16(buf, start, end) == want).tolist()):
                f = opened[i]
                if not same:
                    result[f.stream] = {"error": "frame CRC-16 differs"}
                elif "error" not in result[f.stream]:
                    f.end = int(ends[i]) + 2
                    result[f.stream]["frames"].append(f)
                    if "seek" not in result[f.stream]["info"] and f.end < len(streams[f.stream]):
                        waiting.append((f.stream, f.end))
    for s, got in enumerate(result):
        if "frames" in got:
            frames = sorted(got.pop("frames"), key=lambda f: f.start)
            x = np.concatenate([f.samples << f.wasted for f in frames]) if frames else np.zeros(0, np.int64)
            info, at = got["info"], 0
            got["blocks"] = []
            for f in frames:
                got["blocks"].append((at, f.n, f.start))
                at += f.n
            width = 1 if info["bits"] <= 8 else 2
            if info["total"] and info["total"] != len(x):
                result[s] = {"error": "sample count differs from STREAMINFO"}
            elif any(info["md5"]) and hashlib.md5(x.astype(f"<i{width}").tobytes()).digest() != info["md5"]:
                result[s] = {"error": "MD5 of the samples differs"}
            else:
                got["samples"] = x
    return result
