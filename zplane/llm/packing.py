"""Mixture-controlled packing of token ids into sequences of fixed length.

Each source is a queue of documents. Queues are served in blocks by deficit round robin: every source
earns credit at its target rate, and the block whose midpoint its source's credit reaches first goes
next, so at any moment each source is within one block of its target and what a window lacks is carried
to the next. That order has a closed form: how many blocks of every other source come before a given
block follows from integer ratios of the rates. So each partition places its own documents from the
token totals of all partitions and sources alone; no queue is ever walked by one task, and deficits carry
across windows and partitions by arithmetic. All sequences are full; the remainder is cut at powers of
two, so nothing is padded.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.llm.unit_table import UnitTable
from zplane.session import checkpoint, ship

LENGTH, BLOCK = 4096, 256
_ENDS = "</w>"
#: Chunks of Latin-1 letters and ASCII marks other than the apostrophe, and the words that they are cut into.
_LETTERS, _MARKS = "A-Za-zÀ-ÖØ-öø-ÿ", r"!-&(-/:-@\[-`{-~"
_UNUSUAL = re.compile(f"[^{_LETTERS} \n.,]").search
_WORDS = re.compile(f"^[{_LETTERS}]+$", re.M)
_SIMPLE, _PARTS = re.compile(f"[{_LETTERS}{_MARKS}]+"), re.compile(f"[{_LETTERS}]+|[{_MARKS}]+")


class WordEncoder:
    """Ids of whole texts by a tokenizers file whose pieces never cross blanks, each blank-separated chunk encoded once.

    Chunks are made distinct in Arrow. What is known of a chunk (its bytes, and where its ids lie in a pool)
    is kept for `most` of them, in a table that compares bytes. New chunks of Latin-1 letters and ASCII marks are cut into words, many of which are encoded in one
    call and parted at word-end pieces; any other new chunk is encoded by itself. A text that holds a
    special token's string goes to the library whole.
    """

    def __init__(self, path: str, most: int = 4_000_000):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.t = Tokenizer.from_file(path)
        vocab = self.t.get_vocab(with_added_tokens=True)
        self.special = [t.content for t in self.t.get_added_tokens_decoder().values()]
        self.kind = np.dtype("<u2" if max(vocab.values()) < 1 << 16 else "<u4")
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for s, i in vocab.items() if s.endswith(_ENDS)]] = True
        self.most = most
        self._reset()

    def _reset(self) -> None:
        self.table, self.starts = UnitTable(), np.zeros(1 << 16, np.int32)  # where the ids of each slot begin, and the end
        self.pool, self.used = np.zeros(1 << 20, self.kind), 0

    def _one(self, chunk: str) -> np.ndarray:
        return np.array(self.t.encode(chunk, add_special_tokens=False).ids, self.kind)

    def _learn(self, new: list[str]) -> list[bytes]:
        """Packed ids of chunks that were not seen before."""
        got: dict[str, bytes] = {"": b""}
        words = _WORDS.findall("\n".join(new))  # one pass in C over all chunks that are one word
        composed, more = [], set()
        if len(words) < len(new):
            for c in set(new).difference(words):
                if _SIMPLE.fullmatch(c):
                    parts = _PARTS.findall(c)
                    composed.append((c, parts))
                    more.update(parts)
                elif c:
                    got[c] = self._one(c).tobytes()
            words += more.difference(words)
        some = [words[lo : lo + 250] for lo in range(0, len(words), 250)]
        size = self.kind.itemsize
        for lo in range(0, len(some), 40):
            parts = some[lo : lo + 40]
            for part, found in zip(parts, self.t.encode_batch_fast([" ".join(p) for p in parts], add_special_tokens=False)):
                ids = np.array(found.ids, self.kind)
                cut = np.flatnonzero(self.ends[ids]) + 1
                if len(cut) != len(part):  # not one word each after all
                    got.update((c, self._one(c).tobytes()) for c in part)
                    continue
                raw, to = ids.tobytes(), (cut * size).tolist()
                got.update(zip(part, map(raw.__getitem__, map(slice, [0, *to], to))))
        for c, parts in composed:
            got[c] = b"".join([got[w] for w in parts])
        return [got[c] for c in new]

    def _add(self, slots: np.ndarray, packed: list[bytes]) -> None:
        ids = np.frombuffer(b"".join(packed), self.kind)
        n = np.fromiter(map(len, packed), np.int32, len(packed)) // self.kind.itemsize
        while self.used + len(ids) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        self.pool[self.used : self.used + len(ids)] = ids
        while len(self.starts) <= len(self.table):
            self.starts = np.concatenate([self.starts, np.zeros_like(self.starts)])
        self.starts[slots + 1] = self.used + np.cumsum(n)
        self.used += len(ids)

    def _chunks(self, chunks) -> tuple[np.ndarray, np.ndarray]:
        """(start in the pool, ids) of distinct chunks (an Arrow array of large strings)."""
        import pyarrow as pa

        if len(self.table) + len(chunks) > self.most or self.used > 1 << 30:
            self._reset()
        slot, h = self.table.find(chunks)
        new = np.flatnonzero(slot < 0)
        if len(new):
            some = chunks.take(pa.array(new))
            slot[new] = self.table.add(some, h[new])
            self._add(slot[new], self._learn(some.to_pylist()))
        start = self.starts[slot].astype(np.int64)
        return start, self.starts[slot + 1] - start

    def __call__(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts one after the other, where each text's ids begin and the end)."""
        import pyarrow as pa
        import pyarrow.compute as pc

        whole: dict[int, np.ndarray] = {}
        plain = []
        for i, t in enumerate(texts):
            if "<|" in t and any(s in t for s in self.special):
                whole[i] = self._one(t)
                t = ""
            elif not (_UNUSUAL(t) or ".." in t or ".," in t or ",." in t or ",," in t):
                t = t.replace(".", " .").replace(",", " ,")  # a mark by itself is a word, so fewer chunks differ
            plain.append(t.replace("\n", " "))
        cut = pc.split_pattern(pa.array(plain, pa.large_string()), " ")
        coded = cut.flatten().dictionary_encode()
        start, n = self._chunks(coded.dictionary)
        at = coded.indices.to_numpy()
        n = n[at]
        ends = np.cumsum(n)
        flat = self.pool[np.repeat(start[at] - (ends - n), n) + np.arange(int(n.sum()))]
        begins = np.append(0, ends)[cut.offsets.to_numpy()]
        if not whole:
            return flat, begins
        docs = [whole.get(i, flat[begins[i] : begins[i + 1]]) for i in range(len(texts))]
        return np.concatenate(docs), np.cumsum([0, *map(len, docs)])


class Schedule:
    """Where the tokens of each source's queue lie in the packed stream.

    totals: tokens of each source; rates: its target rate (default: in proportion to its blocks).
    """

    def __init__(self, totals: list[int], rates: list[int] | None = None, block: int = BLOCK, length: int = LENGTH):
        self.block, self.length = block, length
        self.totals = totals
        self.blocks = [-(-t // block) for t in totals]
        self.rates = rates or [max(1, b) for b in self.blocks]
        self.n = sum(totals)
        self.full = self.n // length
        tail, at, ends = self.n % length, self.full * length, []
        for bit in range(tail.bit_length() - 1, -1, -1):
            if tail >> bit & 1:
                at += 1 << bit
                ends.append(at)
        self.tail_ends = np.array(ends, np.int64)

    def block_starts(self, s: int, first: int, last: int) -> np.ndarray:
        """Stream positions of blocks first..last of source s."""
        big = (2 * last + 1) * max(self.rates) >= 1 << 61
        k = np.arange(first, last + 1)
        k = k.astype(object) if big else k
        out = np.zeros(len(k), object if big else np.int64)
        for o, (rate, blocks, total) in enumerate(zip(self.rates, self.blocks, self.totals)):
            if o == s:
                before = k
            else:
                lead, den = (2 * k + 1) * rate - self.rates[s], 2 * self.rates[s]
                before = lead // den + 1 if o < s else -(-lead // den)  # of equal credit the earlier source goes first
                before = np.maximum(0, np.minimum(blocks, before))
            out = out + np.minimum(before * self.block, total)
        return out.astype(np.int64)

    def sequence_of(self, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(sequence, offset) of stream positions."""
        seq, off = pos // self.length, pos % self.length
        late = pos >= self.full * self.length
        if late.any():
            i = np.searchsorted(self.tail_ends, pos[late], side="right")
            begins = np.concatenate([[self.full * self.length], self.tail_ends])[i]
            seq[late], off[late] = self.full + i, pos[late] - begins
        return seq, off

    def pieces(self, s: int, start: int, sizes: list[int]) -> tuple[np.ndarray, ...]:
        """(document, start in it, length, sequence, offset) of consecutive documents from queue position start on."""
        ends = start + np.cumsum(np.array(sizes, np.int64))
        stop = int(ends[-1])
        first, last = start // self.block, (stop - 1) // self.block
        base = self.block_starts(s, first, last)
        edges = np.arange(first, last + 1, dtype=np.int64) * self.block
        # within a block the stream is contiguous; it may cross one end of a sequence, or several in the tail
        cross = []
        hi = np.minimum(edges + self.block, self.totals[s]) - edges + base
        nxt = (base // self.length + 1) * self.length
        inside = (nxt < hi) & (nxt <= self.full * self.length)
        cross.append((edges + nxt - base)[inside])
        for e in self.tail_ends.tolist():
            inside = (base < e) & (e < hi)
            cross.append((edges + e - base)[inside])
        cut = np.unique(np.concatenate([[start], ends, edges, *cross]))
        cut = cut[(cut >= start) & (cut <= stop)]
        lo, size = cut[:-1], np.diff(cut)
        pos = base[lo // self.block - first] + lo % self.block
        doc = np.searchsorted(ends, lo, side="right")
        seq, off = self.sequence_of(pos)
        join = np.zeros(len(lo), bool)  # pieces that go on where the one before ends
        join[1:] = (doc[1:] == doc[:-1]) & (seq[1:] == seq[:-1]) & (off[1:] == off[:-1] + size[:-1])
        keep = np.flatnonzero(~join)
        size = np.add.reduceat(size, keep) if len(keep) else size
        begin = np.concatenate([[start], ends[:-1]])
        return doc[keep], (lo - begin[doc])[keep], size, seq[keep], off[keep]


def _slices(batch, most: int = 6 << 20):
    """Rows of a batch (text in column 2) in slices of about `most` bytes, or one longer row."""
    import pyarrow.compute as pc

    size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(2)), 0).to_numpy())
    lo = 0
    while lo < batch.num_rows:
        before = int(size[lo - 1]) if lo else 0
        hi = max(lo + 1, int(np.searchsorted(size, before + most, side="right")))
        yield batch.slice(lo, hi - lo)
        lo = hi


def pack(docs: DataFrame, tokenizer: str, end_id: int = 2, rates: dict | None = None, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", with_ids: bool = True, order_cols: tuple[str, ...] = ()) -> DataFrame:
    """One row for each piece: (doc_id, source, start, length, ids_crc32, doc_tokens, sequence_id, offset[, ids]).

    A document is its text's ids and end_id; null text counts as empty (just end_id). Null sources form
    one queue. Queues are ordered by order_cols, then id; rows that repeat an id by a hash of their text. rates gives a
    source's target rate (relative integers; default in proportion to its tokens). An empty table gives
    no pieces.
    """
    spark = docs.sparkSession
    ship(spark)
    picked = docs.select(F.col(source_col).cast("string").alias("source"), F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"), *(F.col(c).alias(f"__o{i}") for i, c in enumerate(order_cols)))
    order = [F.col("source").asc_nulls_last(), *(F.col(f"__o{i}") for i in range(len(order_cols))), F.col("doc_id").asc_nulls_last()]
    queued = picked.repartitionByRange(*order).sortWithinPartitions(*order, F.xxhash64("text")).select("source", "doc_id", "text")

    def encode(batches):
        import pyarrow as pa

        from zplane.llm.packing import WordEncoder
        from zplane.session import worker_cache

        enc = worker_cache(("words", tokenizer), lambda: WordEncoder(tokenizer))
        for b in batches:
            for part in _slices(b):
                flat, begins = enc(part.column(2).to_pylist())
                end = np.array([end_id], enc.kind).tobytes()
                ids = [flat[x:y].tobytes() + end for x, y in zip(begins[:-1].tolist(), begins[1:].tolist())]
                n = np.diff(begins) + 1
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(n, pa.int64()), pa.array(ids, pa.binary())], ["source", "doc_id", "n", "ids"])

    coded = checkpoint(queued.mapInArrow(encode, "source string, doc_id long, n long, ids binary"))
    sums = coded.groupBy(F.spark_partition_id().alias("part"), "source").agg(F.sum("n").alias("n")).collect()  # partitions + sources rows
    names = sorted({r["source"] for r in sums}, key=lambda s: (s is None, (s or "").encode()))
    at = {s: i for i, s in enumerate(names)}
    totals, starts = [0] * len(names), {}
    for r in sorted(sums, key=lambda r: r["part"]):
        starts[r["part"], at[r["source"]]] = totals[at[r["source"]]]
        totals[at[r["source"]]] += r["n"]
    plan = Schedule(totals, [max(1, int(rates.get(s, 1))) for s in names] if rates else None)

    def place(batches):
        import zlib

        import pyarrow as pa
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        queue = {s: n for (p, s), n in starts.items() if p == part}
        for b in batches:
            source, doc, n, ids = (c.to_pylist() for c in b.columns)
            lo = 0
            while lo < len(n):
                hi = lo
                while hi < len(n) and source[hi] == source[lo] and hi - lo < 2000:
                    hi += 1
                s = at[source[lo]]
                d, start, size, seq, off = plan.pieces(s, queue[s], n[lo:hi])
                queue[s] += sum(n[lo:hi])
                texts, crcs = [], []
                last, x = -1, None
                for i, a, m in zip(d.tolist(), start.tolist(), size.tolist()):
                    if i != last:
                        raw = ids[lo + i]
                        last, x = i, np.frombuffer(raw, f"<u{len(raw) // n[lo + i]}").astype("<u4")
                    raw = x[a : a + m].tobytes()
                    crcs.append(zlib.crc32(raw))
                    texts.append(raw)
                of = [lo + i for i in d.tolist()]
                cols = [
                    pa.array([doc[i] for i in of], pa.int64()), pa.array([source[i] for i in of], pa.string()), pa.array(start), pa.array(size), pa.array(crcs, pa.int64()),
                    pa.array([n[i] for i in of], pa.int64()), pa.array(seq), pa.array(off),
                ]
                names = ["doc_id", "source", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
                if with_ids:
                    cols.append(pa.array([np.frombuffer(t, "<u4").astype(np.int32) for t in texts], pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names)
                lo = hi

    schema = "doc_id long, source string, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    return coded.mapInArrow(place, schema + (", ids array<int>" if with_ids else ""))
