"""Removal of repeated byte strings by a prefix-free parse of the corpus.

A rolling hash of every K bytes picks triggers: in each window of LENGTH bytes the K bytes with the least
hash. The windows that share a trigger make one phrase (their run, with the bytes that the last one
reaches), so every window of LENGTH bytes lies in exactly one phrase, and equal windows lie at the same
offset from equal triggers. The distinct phrases (by a 128-bit digest of their bytes) are the dictionary,
the phrases in document order the parse. Of equal phrases only the first in the parse can hold new windows.

Where a trigger has several phrases, a window is a suffix of the dictionary text that ends before the
trigger, joined to a prefix of the parse text that follows from it. Both sides get a suffix array with its
lengths of common prefixes: one over the texts from the trigger on, one over the texts before it, read
backwards. Cut at depth LENGTH - o, the first gives classes of equal continuations, the second, cut at
depth o, classes of equal suffixes; a pair of classes is a class of equal windows o bytes before the
trigger, and the place of the phrase in the parse puts each class in corpus order. All of this compares
bytes. A trigger with very many phrases would gather in one task; its windows are dealt out by digests of
their own bytes instead.

Tasks take one bucket of triggers at a time, and the number of buckets grows with the input.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.llm import shingles as sh
from zplane.session import estimated_bytes, release, ship, stored

LENGTH, K = 100, 24
#: Buckets at least, and bytes of input (as stored) for each.
BUCKETS, BUCKET_BYTES = 256, 4 << 20
#: Phrases of one trigger that a map task sends on, and that one task compares, before the trigger counts as hot.
HOT_LOCAL, HOT = 64, 4096
#: Phrases that are compared at once, and bytes of text that a parse task takes at once.
_AT_ONCE, _SLICE = 20_000, 8 << 20
_U = np.uint64
_SEGMENT = 1 << 20
_NULL = -(1 << 63)
_COLS = ("kind", "bucket", "doc", "lo", "n", "off", "h", "blob")
_ROW = "kind int, bucket int, doc long, lo long, n int, off int, h long, blob binary"
#: Kinds of rows: packed phrases, repeated windows, phrases to compare, phrases of hot triggers, packed contexts, packed windows.
PHRASES, REPEAT, COMPARE, HOTTER, CONTEXTS, WINDOWS = range(6)


def parse(buf: np.ndarray, begins: np.ndarray, length: int = LENGTH, k: int = K):
    """The phrases of texts that lie in buf at begins[i]..begins[i+1]: (first window, windows, trigger, trigger hash)."""
    none = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    if len(buf) < length:
        return none
    p = sh.prefix_hash(buf)
    out = []
    ok = np.zeros(len(buf), bool)
    for a, b in zip(begins[:-1].tolist(), begins[1:].tolist()):
        if b - a >= length:
            ok[a : b - length + 1] = True
    w = length - k + 1
    for lo in range(0, len(buf) - length + 1, _SEGMENT):
        hi = min(lo + _SEGMENT, len(buf) - length + 1)  # windows lo..hi-1
        at = np.arange(lo, hi + w - 1)
        grams = sh.range_hash(p, at, at + k)
        m = len(grams)
        key = np.full(-(-m // w) * w, np.iinfo(np.uint64).max, np.uint64)
        key[:m] = (grams >> _U(24) << _U(24)) | np.arange(m, dtype=np.uint64)  # of equal hashes the first
        rows = key.reshape(-1, w)
        left = np.minimum.accumulate(rows, 1).ravel()
        right = np.minimum.accumulate(rows[:, ::-1], 1)[:, ::-1].ravel()
        trigger = (np.minimum(right[: hi - lo], left[w - 1 : w - 1 + hi - lo]) & _U(0xFFFFFF)).astype(np.int64)
        v = np.flatnonzero(ok[lo:hi])
        if not len(v):
            continue
        t = trigger[v]
        first = np.flatnonzero(np.append(True, (t[1:] != t[:-1]) | (v[1:] != v[:-1] + 1)))
        run = np.diff(np.append(first, len(v)))
        start = v[first] + lo
        out.append((start, run, t[first] + lo, grams[t[first]]))
    return tuple(np.concatenate(c) for c in zip(*out)) if out else none


def _pack(*arrays: np.ndarray) -> bytes:
    """Columns, zlib-packed where they are sorted or small."""
    parts = [zlib.compress(np.diff(a, prepend=a.dtype.type(0)).tobytes(), 1) if a.dtype == np.int64 else a.tobytes() for a in arrays]
    return np.array([len(x) for x in parts], "<u4").tobytes() + b"".join(parts)


def _unpack(blob: bytes, kinds: list) -> list[np.ndarray]:
    sizes = np.frombuffer(blob, "<u4", len(kinds))
    at, out = 4 * len(kinds), []
    for size, kind in zip(sizes.tolist(), kinds):
        raw = blob[at : at + size]
        out.append(np.cumsum(np.frombuffer(zlib.decompress(raw), kind)) if kind is np.int64 else np.frombuffer(raw, kind))
        at += size
    return out


def _rows(_kind: int, **cols):
    """A record batch of _ROW; missing columns are 0 or null."""
    import pyarrow as pa

    size = len(next(iter(cols.values())))
    types = {"kind": pa.int32(), "bucket": pa.int32(), "doc": pa.int64(), "lo": pa.int64(), "n": pa.int32(), "off": pa.int32(), "h": pa.int64(), "blob": pa.binary()}
    out = []
    for c in _COLS:
        if c == "kind":
            out.append(pa.array(np.full(size, _kind, np.int32)))
        elif c not in cols:
            out.append(pa.nulls(size, types[c]) if c == "blob" else pa.array(np.zeros(size, types[c].to_pandas_dtype())))
        else:
            out.append(pa.array(cols[c], types[c]))
    return pa.RecordBatch.from_arrays(out, list(_COLS))


def _digests(raw: bytes, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """128-bit digests of raw[begin:end], as two columns."""
    from hashlib import blake2b

    found = b"".join([blake2b(raw[a:z], digest_size=16).digest() for a, z in zip(begin.tolist(), end.tolist())])
    both = np.frombuffer(found, "<u8").reshape(-1, 2)
    return both[:, 0], both[:, 1]


def _spread_by(x: np.ndarray, buckets: int) -> np.ndarray:
    return (sh.mix(x.astype(np.uint64)) % _U(buckets)).astype(np.int32)


def _buckets_of(batches):
    """(bucket, kinds, blobs) of rows sorted by bucket, one bucket at a time; rows without a blob as they are (None, batch, None)."""
    import pyarrow as pa
    import pyarrow.compute as pc

    now, kinds, blobs = None, [], []
    for b in batches:
        packed = pc.is_valid(b.column(7))
        rest = b.filter(pc.invert(packed))
        if rest.num_rows:
            yield None, pa.RecordBatch.from_arrays(rest.columns, list(_COLS)), None
        some = b.filter(packed)
        for kind, bucket, blob in zip(some.column(0).to_pylist(), some.column(1).to_pylist(), some.column(7).to_pylist()):
            if bucket != now:
                if blobs:
                    yield now, kinds, blobs
                now, kinds, blobs = bucket, [], []
            kinds.append(kind)
            blobs.append(blob)
    if blobs:
        yield now, kinds, blobs


def _merged(doc, lo, hi):
    """Overlapping or touching ranges of a document joined."""
    order = np.lexsort((lo, doc))
    doc, lo, hi = doc[order], lo[order], hi[order]
    if not len(doc):
        return doc, lo, hi
    new = np.append(True, doc[1:] != doc[:-1])
    reach = hi.copy()
    at = np.flatnonzero(new)
    base = np.repeat(np.arange(len(at)), np.diff(np.append(at, len(doc)))) * (int(hi.max()) + 1)
    reach = np.maximum.accumulate(hi + base) - base  # the furthest end so far in the document
    first = np.flatnonzero(new | np.append(True, lo[1:] > reach[:-1]))
    last = np.append(first[1:], len(doc)) - 1
    return doc[first], lo[first], reach[last]


def _repeats(doc, lo, n, length, buckets):
    d, a, b = _merged(doc, lo, lo + n - 1 + length)
    return _rows(REPEAT, bucket=_spread_by(d, buckets), doc=d, lo=a, n=(b - a).astype(np.int32)) if len(d) else None


def _first_of(keys: tuple, doc: np.ndarray, lo: np.ndarray):
    """order by keys, doc, lo; for each row whether it begins a group, and whether an earlier equal one exists."""
    order = np.lexsort((lo, doc, *reversed(keys)))
    new = np.zeros(len(order), bool)
    new[:1] = True
    for k in keys:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    at = np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))
    d, p = doc[order], lo[order]
    later = (d != d[at]) | (p != p[at])
    return order, new, later


def _parse_task(length: int, k: int, buckets: int):
    def some(ids, texts):
        found = []
        for part in sh.in_groups(texts):
            raw = b"".join(texts[part])
            begins = np.concatenate([[0], np.cumsum([len(t) for t in texts[part]])])
            lo, n, trigger, h = parse(np.frombuffer(raw, np.uint8), begins, length, k)
            of = np.searchsorted(begins, lo, side="right") - 1
            found.append((ids[part][of], lo - begins[of], n, trigger - lo, h, *_digests(raw, lo, lo + n - 1 + length)))
        doc, lo, n, off, h, c, c2 = (np.concatenate(x) for x in zip(*found))
        order, new, later = _first_of((h, c, c2, off), doc, lo)
        gone = order[later]
        out = _repeats(doc[gone], lo[gone], n[gone], length, buckets)
        if out:
            yield out
        reps = order[new]  # by trigger, then phrase
        hr = h[reps]
        begin = np.flatnonzero(np.append(True, hr[1:] != hr[:-1])) if len(hr) else np.zeros(0, np.int64)
        many = np.diff(np.append(begin, len(hr)))
        nth = np.arange(len(hr)) - np.repeat(begin, many)
        hot = np.repeat(many > HOT_LOCAL, many)
        direct = reps[hot & (nth >= HOT_LOCAL)]
        if len(direct):
            yield _rows(HOTTER, bucket=_spread_by(doc[direct], buckets), doc=doc[direct], lo=lo[direct], n=n[direct].astype(np.int32), off=off[direct].astype(np.int32), h=h[direct].view(np.int64))
        sent = reps[nth < HOT_LOCAL]
        flag = hot[nth < HOT_LOCAL]
        bucket = (h[sent] % _U(buckets)).astype(np.int64)
        order = np.lexsort((lo[sent], doc[sent], bucket))
        sent, flag, bucket = sent[order], flag[order], bucket[order]
        cut = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])) if len(bucket) else np.zeros(0, np.int64)
        blobs = []
        for x, y in zip(cut.tolist(), [*cut[1:].tolist(), len(bucket)]):
            s = sent[x:y]
            blobs.append(_pack(doc[s], lo[s], n[s].astype(np.uint8), off[s].astype(np.uint8), flag[x:y], h[s], c[s], c2[s]))
        yield _rows(PHRASES, bucket=bucket[cut].astype(np.int32), blob=blobs)

    def run(batches):
        import pyarrow.compute as pc

        from zplane.session import trim, worker_cache

        worker_cache(None)
        for b in batches:
            size = np.cumsum(pc.fill_null(pc.binary_length(b.column(1)), 0).to_numpy())
            ids, lo = b.column(0).to_numpy(), 0
            while lo < b.num_rows:
                hi = max(lo + 1, int(np.searchsorted(size, (int(size[lo - 1]) if lo else 0) + _SLICE, side="right")))
                yield from some(ids[lo:hi], [(t or "").encode("utf-8", "surrogatepass") for t in b.column(1).slice(lo, hi - lo).to_pylist()])
                lo = hi
        trim()

    return run


_PHRASE_KINDS = [np.int64, np.int64, np.uint8, np.uint8, bool, np.uint64, np.uint64, np.uint64]


def _compare_phrases(length: int, buckets: int):
    """Equal phrases: all but the first repeat. Triggers with several phrases: their first places go on."""

    def run(batches):
        from zplane.session import trim, worker_cache

        worker_cache(None)
        for bucket, kinds, blobs in _buckets_of(batches):
            if bucket is None:
                yield kinds
                continue
            doc, lo, n, off, flag, h, c, c2 = (np.concatenate(x) for x in zip(*(_unpack(x, _PHRASE_KINDS) for x in blobs)))
            order, new, later = _first_of((h, c, c2, off), doc, lo)
            gone = order[later]
            out = _repeats(doc[gone], lo[gone], n[gone].astype(np.int64), length, buckets)
            if out:
                yield out
            reps = order[new]
            hr = h[reps]
            begin = np.flatnonzero(np.append(True, hr[1:] != hr[:-1]))
            many = np.diff(np.append(begin, len(hr)))
            flags = np.logical_or.reduceat(flag[order], np.flatnonzero(np.append(True, h[order][1:] != h[order][:-1])))
            hot = np.repeat(flags | (many > HOT), many)
            for kind, pick in ((HOTTER, reps[hot]), (COMPARE, reps[~hot & np.repeat(many > 1, many)])):
                if len(pick):
                    yield _rows(kind, bucket=_spread_by(doc[pick], buckets), doc=doc[pick], lo=lo[pick], n=n[pick].astype(np.int32), off=off[pick].astype(np.int32), h=h[pick].view(np.int64))
        trim()

    return run


_CONTEXT_KINDS = [np.int64, np.int64, np.uint8, np.uint8, np.uint64]
_WINDOW_KINDS = [np.int64, np.int64, np.uint64, np.uint64]


def _context_task(length: int, buckets: int):
    """Fetch the bytes of the phrases to compare: whole contexts by trigger, windows of hot triggers by their own digest."""

    def some(docs, texts, asked):
        packs: dict[int, list] = {}
        wins: list = []
        for doc, text, rows in zip(docs, texts, asked):
            raw = (text or "").encode("utf-8", "surrogatepass")
            for kind, lo, n, off, h in zip(*rows):
                if lo + n - 1 + length > len(raw):  # another row with this id is shorter
                    continue
                if kind == COMPARE:
                    h &= (1 << 64) - 1
                    packs.setdefault(h % buckets, []).append((doc, lo, n, off, h, raw[lo : lo + n - 1 + length]))
                else:
                    s = np.arange(lo, lo + n)
                    wins.append((np.full(n, doc, np.int64), s, *_digests(raw, s, s + length)))
        at, blobs = [], []
        for i, rows in packs.items():
            rows.sort(key=lambda r: (r[0], r[1]))
            meta = _pack(*(np.array([r[j] for r in rows], t) for j, t in enumerate(_CONTEXT_KINDS)))
            at.append(i)
            blobs.append(np.array([len(meta)], "<u4").tobytes() + meta + zlib.compress(b"".join(r[5] for r in rows), 1))
        if at:
            yield _rows(CONTEXTS, bucket=np.array(at, np.int32), blob=blobs)
        if wins:
            doc, lo, h, h2 = (np.concatenate(x) for x in zip(*wins))
            order, new, later = _first_of((h, h2), doc, lo)
            gone, kept = order[later], order[new]
            out = _repeats(doc[gone], lo[gone], np.ones(len(gone), np.int64), length, buckets)
            if out:
                yield out
            bucket = (h[kept] % _U(buckets)).astype(np.int64)
            order = np.lexsort((lo[kept], doc[kept], bucket))
            kept, bucket = kept[order], bucket[order]
            cut = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))
            spans = [kept[x:y] for x, y in zip(cut.tolist(), [*cut[1:].tolist(), len(bucket)])]
            yield _rows(WINDOWS, bucket=bucket[cut].astype(np.int32), blob=[_pack(doc[s], lo[s], h[s], h2[s]) for s in spans])

    def run(batches):
        import pyarrow.compute as pc

        from zplane.session import trim, worker_cache

        worker_cache(None)
        for b in batches:
            size = np.cumsum(pc.fill_null(pc.binary_length(b.column(1)), 0).to_numpy())
            lo = 0
            while lo < b.num_rows:
                hi = max(lo + 1, int(np.searchsorted(size, (int(size[lo - 1]) if lo else 0) + _SLICE, side="right")))
                docs, texts, *asked = (c.slice(lo, hi - lo).to_pylist() for c in b.columns)
                yield from some(docs, texts, zip(*asked))
                lo = hi
        trim()

    return run


def _suffix_array(h: np.ndarray, texts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the rows of texts (bytes, padded) by h and then bytes, and how many bytes each shares with the one before (-1: another h)."""
    m, wide = texts.shape
    padded = np.zeros((m, -(-wide // 8) * 8), np.uint8)
    padded[:, :wide] = texts
    order = np.lexsort((*padded.view(">u8").astype(np.uint64).T[::-1], h))
    rows = texts[order]
    differ = rows[1:] != rows[:-1]
    common = np.where(differ.any(1), differ.argmax(1), wide)
    return order, np.append(-1, np.where(h[order][1:] != h[order][:-1], -1, common))


def equal_windows(doc, lo, n, off, h, buf, begin, length: int):
    """(doc, start) of windows that equal an earlier one with the same trigger hash and offset.

    Phrase i holds n[i] windows from lo[i] on; its bytes lie in buf from begin[i] on, its trigger off[i] bytes later.
    """
    order = np.lexsort((lo + off, doc))  # corpus order of the triggers
    doc, lo, n, off, h, begin = (x[order] for x in (doc, lo, n, off, h, begin))
    m, k = len(doc), np.arange(length)
    after = n - 1 + length - off  # bytes from the trigger on
    right = np.where(k < after[:, None], buf[np.minimum((begin + off)[:, None] + k, len(buf) - 1)], 0).astype(np.uint8)
    far = max(1, int(off.max()))
    left = np.where(k[:far] < off[:, None], buf[np.maximum((begin + off)[:, None] - 1 - k[:far], 0)], 0).astype(np.uint8)
    (by_right, r), (by_left, l) = _suffix_array(h, right), _suffix_array(h, left)
    place = lo + off
    out = []
    goes_on, ends_so = np.empty(m, np.int64), np.empty(m, np.int64)
    for o in range(int((off - n).min()) + 1, int(off.max()) + 1):
        mine = np.flatnonzero((off >= o) & (off - n < o))
        if len(mine) < 2:
            continue
        goes_on[by_right] = np.cumsum(r < length - o)
        ends_so[by_left] = np.cumsum(l < o)
        both = goes_on[mine] * (m + 1) + ends_so[mine]
        at = np.argsort(both, kind="stable")
        same = both[at]
        first = np.maximum.accumulate(np.where(np.append(True, same[1:] != same[:-1]), np.arange(len(at)), 0))
        of, origin = mine[at], mine[at[first]]
        later = of[(doc[of] != doc[origin]) | (place[of] != place[origin])]
        out.append((doc[later], place[later] - o))
    if not out:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return tuple(np.concatenate(x) for x in zip(*out))


def _compare_windows(length: int, buckets: int):
    """Equal windows of the compared contexts and of hot triggers: all but the first repeat."""

    def run(batches):
        from zplane.session import trim, worker_cache

        worker_cache(None)
        for bucket, kinds, blobs in _buckets_of(batches):
            if bucket is None:
                yield kinds
                continue
            windows = [_unpack(x, _WINDOW_KINDS) for kind, x in zip(kinds, blobs) if kind == WINDOWS]
            if windows:
                doc, lo, h, h2 = (np.concatenate(x) for x in zip(*windows))
                windows.clear()
                order, _, later = _first_of((h, h2), doc, lo)
                gone = order[later]
                out = _repeats(doc[gone], lo[gone], np.ones(len(gone), np.int64), length, buckets)
                if out:
                    yield out
            sizes = [int(np.frombuffer(x, "<u4", 1)[0]) if kind == CONTEXTS else 0 for kind, x in zip(kinds, blobs)]
            contexts = [(_unpack(x[4 : 4 + size], _CONTEXT_KINDS), x[4 + size :]) for size, x in zip(sizes, blobs) if size]
            if not contexts:
                continue
            doc, lo, n, off, h = (np.concatenate(x) for x in zip(*(m for m, _ in contexts)))
            buf = np.frombuffer(b"".join(zlib.decompress(x) for _, x in contexts), np.uint8)
            contexts.clear()
            n, off = n.astype(np.int64), off.astype(np.int64)
            begin = np.cumsum(n - 1 + length) - (n - 1 + length)
            order = np.argsort(h, kind="stable")
            cut, at = np.flatnonzero(np.append(True, h[order][1:] != h[order][:-1])), 0
            while at < len(order):  # whole triggers, so that only a part of the windows is spread out at a time
                past = np.searchsorted(cut, at + _AT_ONCE)
                to = int(cut[past]) if past < len(cut) else len(order)
                i = order[at:to]
                gone, pos = equal_windows(doc[i], lo[i], n[i], off[i], h[i], buf, begin[i], length)
                out = _repeats(gone, pos, np.ones(len(gone), np.int64), length, buckets)
                if out:
                    yield out
                at = to
        trim()

    return run


def repeated_ranges(docs: DataFrame, length: int = LENGTH, k: int = K) -> DataFrame:
    """(doc, lo, hi): byte ranges covered by windows of `length` bytes that start earlier too, not yet merged.

    docs: (doc_id long, text string). Every row is parsed; nothing is broadcast or collected.
    """
    spark = docs.sparkSession
    ship(spark)
    named = docs.select(F.coalesce("doc_id", F.lit(_NULL)).alias("doc"), "text")
    buckets = max(BUCKETS, min(1 << 30, estimated_bytes(named) // BUCKET_BYTES))
    parsed = named.mapInArrow(_parse_task(length, k, buckets), _ROW).repartition("bucket").sortWithinPartitions("bucket")
    found = stored(parsed.mapInArrow(_compare_phrases(length, buckets), _ROW).drop("blob", "bucket"), "phrases")
    release(spark)
    asked = found.where(F.col("kind") != REPEAT).groupBy("doc").agg(F.collect_list(F.struct("kind", "lo", "n", "off", "h")).alias("rows"))
    texts = named.join(asked.hint("shuffle_hash"), "doc").select("doc", "text", *(F.col(f"rows.{c}").alias(c) for c in ("kind", "lo", "n", "off", "h")))
    spread = texts.mapInArrow(_context_task(length, buckets), _ROW).repartition("bucket").sortWithinPartitions("bucket")
    second = stored(spread.mapInArrow(_compare_windows(length, buckets), _ROW).select("doc", "lo", "n"), "windows")
    release(spark)
    both = found.where(F.col("kind") == REPEAT).select("doc", "lo", "n").union(second)
    return both.select("doc", "lo", (F.col("lo") + F.col("n")).alias("hi"))


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, k: int = K, with_kept: bool = True) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, spans[, kept]) of every row.

    Texts are UTF-8 bytes (null: empty); each byte covered by a string of `length` bytes that also starts
    earlier (smaller id, or the same document and an earlier start) is removed; spans are the maximal
    removed ranges. Ids order documents; rows that repeat an id are taken as one document and should
    repeat its text (ranges beyond a shorter text are ignored); null ids come first. Texts shorter than
    `length` stay whole. Other columns are not read.
    """
    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    ranges = repeated_ranges(picked, length, k).groupBy("doc").agg(F.collect_list(F.struct("lo", "hi")).alias("ranges"))
    both = picked.withColumn("doc", F.coalesce("doc_id", F.lit(_NULL))).join(ranges, "doc", "left").select("doc_id", "text", F.col("ranges.lo").alias("lo"), F.col("ranges.hi").alias("hi"))

    def run(batches):
        import hashlib

        import pyarrow as pa
        import pyarrow.compute as pc

        from zplane.session import trim, worker_cache

        worker_cache(None)
        for b in batches:
            size = np.cumsum(pc.fill_null(pc.binary_length(b.column(1)), 0).to_numpy())
            at = 0
            while at < b.num_rows:
                to = max(at + 1, int(np.searchsorted(size, (int(size[at - 1]) if at else 0) + _SLICE, side="right")))
                rows = []
                for doc, text, begins, ends in zip(*(c.slice(at, to - at).to_pylist() for c in b.columns)):
                    raw = (text or "").encode("utf-8", "surrogatepass")
                    spans: list[list[int]] = []
                    for a, z in sorted(zip(begins or (), ends or ())):
                        z = min(z, len(raw))
                        if a >= z:
                            continue
                        if spans and a <= spans[-1][1]:
                            spans[-1][1] = max(spans[-1][1], z)
                        else:
                            spans.append([a, z])
                    kept = b"".join(raw[a:z] for a, z in zip([0, *(s[1] for s in spans)], [*(s[0] for s in spans), len(raw)]))
                    rows.append((doc, len(raw), len(raw) - len(kept), len(spans), hashlib.sha256(kept).hexdigest(), spans, kept))
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.list_(pa.int64())), pa.binary()]
                names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans", "kept"]
                m = 7 if with_kept else 6
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows))[:m], kinds)], names[:m])
                at = to
        trim()

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<array<bigint>>"
    return both.mapInArrow(run, schema + (", kept binary" if with_kept else ""))
