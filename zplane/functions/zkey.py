"""Morton order of floating-point vectors at full precision: comparator, exact binary keys, levels, cells.

Two numbers differ first at some power of two (msb); vectors compare in the dimension where that power is
largest. The exact key makes this a byte comparison: a row of sign bits, then one row of bits for each
exponent of a window planned from the data, dimensions interleaved; magnitudes of negative numbers are
complemented. The number of leading bits that two keys share gives their Morton level.
"""

from __future__ import annotations

import functools
import math
import struct
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from zplane.session import ship

EMAX = {"float": 128, "double": 1024}


def msb_fixed(a: int, b: int) -> int:
    """The highest bit at which two non-negative integers differ (-1 if they are equal)."""
    return (a ^ b).bit_length() - 1


def msb(a: float, b: float, ftype: str = "double") -> float:
    """The power of two of the most significant difference of two numbers; -inf if equal, EMAX if signs differ."""
    a, b = a + 0.0, b + 0.0
    if a == b:
        return -math.inf
    if (a < 0) != (b < 0):
        return EMAX[ftype]
    (ma, ea), (mb, eb) = math.frexp(abs(a)), math.frexp(abs(b))
    if not a or not b:
        return (eb if not a else ea) - 1
    if ea != eb:
        return max(ea, eb) - 1
    return ea - 1 - 52 + msb_fixed(int(math.ldexp(ma, 53)), int(math.ldexp(mb, 53)))


def z_less(p, q) -> bool:
    """The Morton comparator, strict; the first dimension with the largest msb decides."""
    best, k = -math.inf, -1
    for i, (a, b) in enumerate(zip(p, q)):
        m = msb(a, b)
        if m > best:
            best, k = m, i
    return k >= 0 and p[k] < q[k]


def morton_level(p, q) -> float:
    d = len(p)
    ms = [msb(a, b) for a, b in zip(p, q)]
    top = max(ms)
    return -math.inf if top == -math.inf else (top + 1) * d - ms.index(top)


def extent_levels(lvl: int, d: int) -> list[int]:
    """Binary logarithms of a cell's extents; they sum to lvl and differ by one at most."""
    whole, part = divmod(lvl, d)
    return [whole + (i >= d - part) for i in range(d)]


@dataclass(frozen=True)
class KeyPlan:
    """Exponent window of exact keys: rows for top .. low after the row of signs; one window for all dimensions."""

    d: int
    top: int
    low: int

    @property
    def bits(self) -> int:
        return self.d * (self.top - self.low + 2)

    @property
    def bytes(self) -> int:
        return (self.bits + 7) // 8


def window(x: np.ndarray) -> tuple[int, int]:
    """(largest exponent, exponent of the lowest set bit) over finite non-zero numbers; (-1075, 1024) if there are none."""
    x = np.abs(x[(x != 0) & np.isfinite(x)])
    if not len(x):
        return -1075, 1024
    m, e = np.frexp(x)
    whole = np.ldexp(m, 53).astype(np.int64)
    trail = np.frexp((whole & -whole).astype(np.float64))[1] - 1
    return int(e.max()) - 1, int((e - 53 + trail).min())


def plan_of(x: np.ndarray, d: int) -> KeyPlan:
    top, low = window(np.asarray(x, np.float64).ravel())
    return KeyPlan(d, top, low) if top >= low else KeyPlan(d, 0, 0)


def exact_keys(x: np.ndarray, plan: KeyPlan) -> np.ndarray:
    """Fixed-width byte keys (n, bytes) of points x (n, d).

    Each number is 128 bits: its sign, then its magnitude from the top of the window on; eight rows of all dimensions
    are then spread and interleaved at once.
    """
    n, d = x.shape
    rows = plan.top - plan.low + 2
    wide = -(-rows // 8) * 8
    if not 0 < d <= 8 or wide > 128:
        return _keys_by_rows(x, plan)
    x = x + 0.0
    m, e = np.frexp(np.abs(x))
    whole = np.ldexp(m, 53).astype(np.uint64)
    negative = x < 0
    high, low = _shifted(np.zeros_like(whole), whole, e.astype(np.int64) - 53 - plan.low)
    for word, bits in ((high, rows - 65), (low, rows - 1)):  # magnitudes end below the sign
        mask = np.uint64((1 << max(0, min(64, bits))) - 1)
        word &= mask
        word ^= np.where(negative, mask, np.uint64(0))
    sign = np.where(negative, np.uint64(0), np.uint64(1) << np.uint64((rows - 1) % 64))
    if rows > 64:
        high |= sign
    else:
        low |= sign
    high, low = _shifted(high, low, np.full(x.shape, wide - rows))
    out = np.empty((n, wide // 8 * d), np.uint8)
    lut = _spread(d)
    for g in range(wide // 8):
        at = wide - 8 - 8 * g
        byte = ((high >> np.uint64(at - 64)) if at >= 64 else (low >> np.uint64(at))).astype(np.uint8)
        group = lut[byte[:, 0]] << np.uint64(d - 1)
        for i in range(1, d):
            group |= lut[byte[:, i]] << np.uint64(d - 1 - i)
        out[:, g * d : (g + 1) * d] = group.astype(">u8").view(np.uint8).reshape(n, 8)[:, 8 - d :]
    return np.ascontiguousarray(out[:, : plan.bytes])


def _shifted(high: np.ndarray, low: np.ndarray, by: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The 128 bits (high, low) shifted to the left by `by` (to the right where that is negative; high must be 0 there)."""
    up = np.clip(by, 0, 128).astype(np.uint64)
    part, none = up % np.uint64(64), np.uint64(0)
    over = np.where(part > 0, low >> ((np.uint64(64) - part) % np.uint64(64)), none)
    near = up < 64
    h = np.where(near, high << part | over, np.where(up < 128, low << part, none))
    down = np.clip(-by, 0, 64).astype(np.uint64)
    return h, np.where(near, np.where(down < 64, (low << part) >> (down % np.uint64(64)), none), none)


@functools.cache
def _spread(d: int) -> np.ndarray:
    """For each byte, its bits d places apart."""
    byte = np.arange(256, dtype=np.uint64)
    out = np.zeros(256, np.uint64)
    for b in range(8):
        out |= (byte >> np.uint64(b) & np.uint64(1)) << np.uint64(b * d)
    return out


def key_rows(column) -> np.ndarray:
    """(n, bytes) of an Arrow column of keys of one width, without an object for each."""
    import pyarrow as pa

    a = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if not len(a):
        return np.zeros((0, 0), np.uint8)
    at = np.frombuffer(a.buffers()[1], np.int64 if pa.types.is_large_binary(a.type) else np.int32)[a.offset : a.offset + len(a) + 1]
    return np.frombuffer(a.buffers()[2], np.uint8)[at[0] : at[-1]].reshape(len(a), -1)


def key_array(keys: np.ndarray):
    """The Arrow array of the rows of keys (n, bytes), the other way round."""
    import pyarrow as pa

    n, width = keys.shape
    if n * width >= 1 << 31:
        return pa.array([k.tobytes() for k in keys], pa.binary())
    return pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(np.arange(n + 1, dtype=np.int32) * np.int32(width)), pa.py_buffer(np.ascontiguousarray(keys))])


def _keys_by_rows(x: np.ndarray, plan: KeyPlan) -> np.ndarray:
    """exact_keys for any plan, bit by bit."""
    n, d = x.shape
    x = x + 0.0
    m, e = np.frexp(np.abs(x))
    whole = np.ldexp(m, 53).astype(np.uint64)
    negative = x < 0
    rows = plan.top - plan.low + 2
    bits = np.zeros((n, plan.bytes * 8), np.uint8)
    bits[:, :d] = ~negative
    for r in range(1, rows):
        shift = (plan.top - (r - 1)) - (e - 53)
        ok = (shift >= 0) & (shift < 53) & (whole != 0)
        bit = (whole >> np.where(ok, shift, 0).astype(np.uint64)) & np.uint64(1)
        bits[:, r * d : (r + 1) * d] = np.where(ok, bit, 0).astype(np.uint8) ^ negative
    return np.packbits(bits, axis=1)


def common_bits(a: np.ndarray, b: np.ndarray, plan: KeyPlan) -> np.ndarray:
    """Leading bits that rows of a and b share (plan.bits where they are equal)."""
    if not len(a):
        return np.zeros(0, np.int64)
    x = a ^ b
    byte = (x != 0).argmax(1)
    v = x[np.arange(len(x)), byte]
    lead = 8 - np.frexp(v.astype(np.float64))[1]
    return np.where(v == 0, plan.bits, byte * 8 + lead).astype(np.int64)


def level_of_bits(b: np.ndarray, plan: KeyPlan) -> np.ndarray:
    """Morton level of two points whose keys share b leading bits; -2^31 for equal points, above EMAX * d - d for different signs."""
    row, k = b // plan.d, b % plan.d
    e = np.where(row == 0, EMAX["double"], plan.top - (row - 1))
    return np.where(b >= plan.bits, -(2**31), (e + 1) * plan.d - k)


def cells(x: np.ndarray, lvl: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(centre, extent) of the Morton cells of level lvl around points x; equal points give the point and 0,
    cells across zero are unbounded (centre 0, extent inf)."""
    n, d = x.shape
    lv = lvl.astype(np.int64)
    point, wide = lv <= -(2**30), lv > EMAX["double"] * d - d
    lv = np.where(point | wide, 0, lv)
    whole, part = lv // d, lv % d
    size = np.ldexp(1.0, (whole[:, None] + (np.arange(d)[None] >= d - part[:, None])).astype(np.int64))
    sign = np.where(x < 0, -1.0, 1.0)
    centre = sign * (np.floor(np.abs(x) / size) * size + size / 2)
    centre = np.where(point[:, None], x, np.where(wide[:, None], 0.0, centre))
    return centre, np.where(point[:, None], 0.0, np.where(wide[:, None], np.inf, size))


# -- columns -----------------------------------------------------------------------------------------
def _vectors(batch, first: int, d: int) -> np.ndarray:
    return np.column_stack([batch.column(first + i).to_numpy(zero_copy_only=False) for i in range(d)]) if d else np.zeros((batch.num_rows, 0))


def plan_key(df: DataFrame, cols: list[str]) -> KeyPlan:
    """The exponent window of all coordinates: two numbers from each task, reduced in Spark."""
    ship(df.sparkSession)

    def run(batches):
        import pyarrow as pa

        from zplane.functions.zkey import _vectors, window

        for b in batches:
            top, low = window(_vectors(b, 0, b.num_columns).ravel())
            yield pa.RecordBatch.from_arrays([pa.array([top], pa.int32()), pa.array([low], pa.int32())], ["top", "low"])

    r = df.select(*(F.col(c).cast("double") for c in cols)).mapInArrow(run, "top int, low int").agg(F.max("top"), F.min("low")).first()
    return KeyPlan(len(cols), r[0], r[1]) if r[0] is not None and r[0] >= r[1] else KeyPlan(len(cols), 0, 0)


def with_zkey(df: DataFrame, cols: list[str], plan: KeyPlan | None = None, mode: str = "exact", box: tuple | None = None) -> DataFrame:
    """df with the column zkey: BINARY exact keys; keys of the coordinates as 32-bit floats (mode float32: 24 bits a
    number, so shorter keys); or a BIGINT of floor(63 / d) bits a dimension (modes morton63 and hilbert, which need box)."""
    if mode == "morton63":
        return df.withColumn("zkey", morton63([F.col(c) for c in cols], box))
    if mode == "hilbert":
        return df.withColumn("zkey", hilbert63([F.col(c) for c in cols], box))
    if mode == "float32":
        names = [f"__f{i}" for i in range(len(cols))]
        return with_zkey(df.withColumns({n: F.col(c).cast("float").cast("double") for n, c in zip(names, cols)}), names, plan).drop(*names)
    if mode != "exact":
        raise ValueError(f"unknown key mode {mode}")
    plan = plan or plan_key(df, cols)
    ship(df.sparkSession)

    @F.arrow_udf("binary")
    def key(*xs):
        from zplane.functions.zkey import exact_keys, key_array

        return key_array(exact_keys(np.column_stack([x.to_numpy(zero_copy_only=False).astype(np.float64) for x in xs]), plan))

    return df.withColumn("zkey", key(*(F.col(c).cast("double") for c in cols)))


def morton_bits(d: int) -> int:
    """Bits of each dimension in a 63-bit key (62 for one dimension, so that cell numbers fit)."""
    return min(62, 63 // d)


def morton63(cols: list[Column], box: tuple) -> Column:
    """The usual integer key: coordinates clamped to box ((low, high) of each dimension), bits interleaved in codegen."""
    d = len(cols)
    bits = morton_bits(d)
    out = F.lit(0).cast("long")
    cells_ = []
    for c, (lo, hi) in zip(cols, box):
        scaled = F.floor((c - lo) / (hi - lo) * float(1 << bits)).cast("long")
        cells_.append(F.least(F.greatest(scaled, F.lit(0).cast("long")), F.lit((1 << bits) - 1).cast("long")))
    for b in range(bits):
        for i, c in enumerate(cells_):
            out = out.bitwiseOR(F.shiftleft(F.shiftright(c, b).bitwiseAND(F.lit(1).cast("long")), b * d + d - 1 - i))
    return out


def hilbert63(cols: list[Column], box: tuple) -> Column:
    """Positions along the Hilbert curve of the cells that morton63 interleaves."""
    bits = morton_bits(len(cols))

    @F.pandas_udf("long")
    def place(*cells_):
        import pandas as pd

        from zplane.functions.zkey import hilbert_index

        return pd.Series(hilbert_index(np.column_stack([c.to_numpy(np.int64) for c in cells_]), bits)) if len(cells_[0]) else pd.Series([], dtype="int64")

    scaled = [F.floor((c - lo) / (hi - lo) * float(1 << bits)).cast("long") for c, (lo, hi) in zip(cols, box)]
    return place(*(F.least(F.greatest(s, F.lit(0).cast("long")), F.lit((1 << bits) - 1).cast("long")) for s in scaled))


def hilbert_index(cells_: np.ndarray, bits: int) -> np.ndarray:
    """Hilbert curve positions of integer cells (n, d): the order that the Morton order is compared with."""
    x = cells_.astype(np.int64).copy()
    d = x.shape[1]
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(d):
            hit = (x[:, i] & q) > 0
            t = np.where(hit, 0, (x[:, 0] ^ x[:, i]) & p)
            x[:, 0] ^= np.where(hit, p, t)
            x[:, i] ^= t if i else 0
        q >>= 1
    for i in range(1, d):
        x[:, i] ^= x[:, i - 1]
    t = np.zeros(len(x), np.int64)
    q = 1 << (bits - 1)
    while q > 1:
        t = np.where((x[:, d - 1] & q) > 0, t ^ (q - 1), t)
        q >>= 1
    x ^= t[:, None]
    out = np.zeros(len(x), np.int64)
    for b in range(bits - 1, -1, -1):
        for i in range(d):
            out = out << 1 | (x[:, i] >> b & 1)
    return out


def float_bits(x: float) -> int:
    return struct.unpack("<q", struct.pack("<d", x))[0]
