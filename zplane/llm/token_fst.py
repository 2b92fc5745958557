"""Token counts from a compiled finite-state transducer.

A piece vocabulary with merge scores (byte-pair encoding with byte fallback) is compiled into a
deterministic transducer over characters. After each prefix, merge encoding ends in exactly one last
piece, and two neighbouring pieces can stand side by side only if encoding their concatenation gives
the two back; so the last piece of a longer prefix follows from the last pieces of the few prefixes
that the current trie node reaches back to. A state is therefore (trie node, those last pieces with
their counts relative to the newest); states are made the first time they are reached, and each
transition is annotated with the change of the emitted-token count.

The blank mark resets the transducer, because no piece holds a blank mark after another character. A
chunk of text thus maps every incoming state to (count, outgoing state) through three parts: a head
that still belongs to the unit that was open, a closed count, and the open unit at its end. These
chunk maps compose associatively, so a long text is counted chunk by chunk and the maps are combined
by a balanced prefix scan.
"""

from __future__ import annotations

import re
from collections import deque
from functools import lru_cache
from typing import NamedTuple

import numpy as np

from zplane.llm.unit_table import UnitTable

BLANK = "▁"
_UNITS = re.compile(r"( +)([^ ]*)")


#: Stands for a prefix at which no later piece can start.
_GONE = ("", 0, False)


class _State:
    __slots__ = ("go", "node", "tail")

    def __init__(self, node: int, tail: tuple):
        self.node, self.tail, self.go = node, tail, {}


class Transducer:
    """The lazily determinised transducer of one vocabulary; memory is bounded by max_states and max_units."""

    def __init__(self, pieces: list[tuple[str, float]], max_states: int = 350_000, max_units: int = 20_000):
        self.score = {p: s for p, s in pieces}
        runs = [len(p) for p in self.score if len(p) > 1 and set(p) == {BLANK}]
        if any(BLANK in p.lstrip(BLANK) for p in self.score):
            raise ValueError("a piece holds a blank mark after another character")
        self.run = max(runs, default=1)
        self.in_run = [self._join_blanks(r, {1, *runs}) for r in range(3 * self.run + 1)]
        for p in [p for p in self.score if len(p) > 1 and p.startswith(BLANK * 2)]:
            if set(p) != {BLANK}:
                raise ValueError("a piece joins several blank marks with text")
            del self.score[p]
        self.max_states, self.max_units = max_states, max_units
        self.fits: dict[tuple[str, str], bool] = {}
        self.back: dict[int, frozenset] = {}
        self.units: dict[str, tuple[int, bool]] = {}
        self.counts = _Counts(self)
        self._trie()
        self._flush()

    # -- compilation ---------------------------------------------------------------------------
    def encode(self, text: str) -> list[str]:
        """Reference merge encoding of a short string (best score first, then leftmost)."""
        parts, score = list(text), self.score
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                s = score.get(parts[i] + parts[i + 1])
                if s is not None and (best is None or s > best):
                    best, at = s, i
            if at < 0:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    @staticmethod
    def _join_blanks(r: int, known: set[int]) -> int:
        """Pieces of a run of r blank marks: all joins score alike, so the leftmost possible one is made first."""
        parts, i = [1] * r, 0
        while i + 1 < len(parts):
            if parts[i] + parts[i + 1] in known:
                parts[i : i + 2] = [parts[i] + parts[i + 1]]
                i = max(0, i - 1)
            else:
                i += 1
        return len(parts)

    def blanks(self, r: int) -> int:
        """Pieces of a run of r blank marks; a longest piece at the left is closed, so runs repeat with its length."""
        full = max(0, -(-(r - 3 * self.run) // self.run))
        return full + self.in_run[r - full * self.run]

    def _trie(self) -> None:
        """Aho-Corasick automaton of the pieces that encoding can produce."""
        self.edges, self.depth, self.ends, self.fail = [{}], [0], [[]], [0]
        for p in self.score:
            if len(p) > 1 and self.encode(p) != [p]:
                continue
            at = 0
            for c in p:
                nxt = self.edges[at].get(c)
                if nxt is None:
                    nxt = self.edges[at][c] = len(self.edges)
                    self.edges.append({})
                    self.depth.append(self.depth[at] + 1)
                    self.ends.append([])
                    self.fail.append(0)
                at = nxt
            self.ends[at].append(p)
        todo = deque(self.edges[0].values())
        while todo:
            at = todo.popleft()
            for c, nxt in self.edges[at].items():
                f = self.fail[at]
                while f and c not in self.edges[f]:
                    f = self.fail[f]
                self.fail[nxt] = self.edges[f].get(c, 0)
                self.ends[nxt] += self.ends[self.fail[nxt]]  # longest first
                todo.append(nxt)

    def _flush(self) -> None:
        self.states: dict[tuple, _State] = {}
        self.entries: dict[tuple, tuple] = {}
        self.start = self._state(0, ((None, 0, False),))

    def _same(self, entry: tuple) -> tuple:
        return self.entries.setdefault(entry, entry)

    def _state(self, node: int, tail: tuple) -> _State:
        key = (node, tail)
        found = self.states.get(key)
        if found is None:
            found = self.states[key] = _State(node, tail)
        return found

    def _starts(self, node: int) -> frozenset:
        """How far back from here a later piece can start: the depths along the failure chain."""
        found = self.back.get(node)
        if found is None:
            at, depths = node, {0}
            while at:
                depths.add(self.depth[at])
                at = self.fail[at]
            found = self.back[node] = frozenset(depths)
        return found

    def _step(self, s: _State, c: str) -> tuple[int, _State]:
        """The annotated transition of state s on character c: (change of the count, next state)."""
        if c not in self.edges[0]:  # no piece: byte fallback, and nothing merges across it
            out = (len(c.encode("utf-8", "surrogatepass")), self._state(0, ((None, 0, s.tail[-1][2]),)))
            s.go[c] = out
            return out
        node = s.node
        while node and c not in self.edges[node]:
            node = self.fail[node]
        node = self.edges[node].get(c, 0)
        for p in self.ends[node]:
            if len(p) > len(s.tail):
                continue
            last, n, lone = s.tail[-len(p)]
            if last is None:
                ok, lone = True, (p == BLANK or lone)
            else:
                ok = self.fits.get((last, p))
                if ok is None:
                    if len(self.fits) > 2_000_000:
                        self.fits.clear()
                    ok = self.fits[(last, p)] = self.encode(last + p) == [last, p]
            if ok:
                tail = (s.tail + ((p, n + 1, lone),))[-(self.depth[node] + 1) :]
                keep = self._starts(node)
                at = len(tail)
                out = (n + 1, self._state(node, tuple(self._same((x[0], x[1] - n - 1, x[2])) if at - i in keep else _GONE for i, x in enumerate(tail, 1))))
                s.go[c] = out
                return out
        raise AssertionError("encoding has no last piece here")

    # -- running -------------------------------------------------------------------------------
    def unit(self, word: str) -> tuple[int, bool]:
        """(tokens of one blank mark followed by word, whether the blank mark stays a token of its own)."""
        found = self.units.get(word)
        if found is None:
            if len(self.states) > self.max_states:
                self._flush()
            elif len(self.units) > self.max_units:
                self.units.clear()
            n, s = 0, self.start
            for c in BLANK + word:
                step = s.go.get(c)
                w, s = step if step is not None else self._step(s, c)
                n += w
            found = (n, s.tail[-1][2])
            if len(word) <= 64:
                self.units[word] = found
        return found

    def run_unit(self, word: str) -> int:
        """Tokens of one blank mark and word, without the memo; a word that begins with a line feed has no blank before it."""
        if len(self.states) > self.max_states:
            self._flush()
        n, s = 0, self.start
        for c in word if word[:1] == "\n" else BLANK + word:
            step = s.go.get(c)
            w, s = step if step is not None else self._step(s, c)
            n += w
        return n

    def open_unit(self, blanks: int, word: str) -> int:
        """Tokens of a run of blank marks and the word after it; runs join last, from the left."""
        if not blanks:
            return 0
        if not word:
            return self.blanks(blanks)
        n, lone = self.unit(word)
        rest = blanks if lone else blanks - 1
        return n - lone + self.blanks(rest)

    def chunk(self, text: str) -> "ChunkMap":
        at = text.find(" ")
        if at < 0:
            return ChunkMap(text, None, 0, "")
        head, last = text[:at], text.rfind(" ")
        first = last
        while first > at and text[first - 1] == " ":
            first -= 1
        inner = text[at:first]
        if "  " not in inner and not (inner and inner[-1] == " "):
            closed = sum(map(self.counts.__getitem__, inner[1:].split(" "))) if inner else 0
        else:
            closed = sum(self.open_unit(len(b), w) for b, w in _UNITS.findall(inner))
        return ChunkMap(head, closed, last - first + 1, text[last + 1 :])

    def compose(self, a: "ChunkMap", b: "ChunkMap") -> "ChunkMap":
        if b.closed is None:
            if a.closed is None:
                return ChunkMap(a.head + b.head, None, 0, "")
            return ChunkMap(a.head, a.closed, a.blanks, a.tail + b.head)
        if a.closed is None:
            return ChunkMap(a.head + b.head, b.closed, b.blanks, b.tail)
        return ChunkMap(a.head, a.closed + self.open_unit(a.blanks, a.tail + b.head) + b.closed, b.blanks, b.tail)

    def count(self, text: str, chunk_chars: int = 1 << 16) -> int:
        """Tokens of a whole text."""
        if not text:
            return 0
        text = " " + text.replace(BLANK, " ")
        maps, at = [], 0
        while at < len(text):
            to = at + chunk_chars
            while to < len(text) and text[to] == " ":  # a run of blanks stays in one chunk
                to += 1
            maps.append(self.chunk(text[at:to]))
            at = to
        while len(maps) > 1:
            maps = [self.compose(*maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
        return maps[0].closed + self.open_unit(maps[0].blanks, maps[0].tail)


class _Counts(dict):
    """Memo of unit counts for the fast path (single blanks)."""

    def __init__(self, t: Transducer):
        self.t = t

    def __missing__(self, word: str) -> int:
        if len(self) > 5 * self.t.max_units:
            self.clear()
        n = self.t.unit(word)[0] if word else 1
        if len(word) <= 64:
            self[word] = n
        return n


class ChunkMap(NamedTuple):
    """What a chunk does to any incoming state: head ends the open unit, closed is the count inside,
    blanks and tail are the unit open at its end. closed is None if the chunk has no blank."""

    head: str
    closed: int | None
    blanks: int
    tail: str


def load_model(path: str) -> Transducer:
    """Compile a sentencepiece byte-pair model file."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    plain = [
        (sp.id_to_piece(i), sp.get_score(i))
        for i in range(sp.get_piece_size())
        if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))
    ]
    return Transducer(plain)


compile_model = lru_cache(maxsize=1)(load_model)


class UnitCounts:
    """Token counts of many texts at once. Units (a blank mark and a word) start from the reset state, so
    the chunk map of each is one number: distinct units of a batch are found in Arrow, those not met before
    go through the transducer, and their counts stay in a table (`most` of them) that compares their bytes.
    Texts with runs of blanks, or longer than a chunk, are counted by composing chunk maps."""

    def __init__(self, fst: Transducer, most: int = 4_000_000, chunk_chars: int = 1 << 16):
        self.fst, self.most, self.chunk_chars = fst, most, chunk_chars
        self.feed_resets = "\n" not in fst.edges[0]
        self._reset()

    def _reset(self) -> None:
        self.table, self.known = UnitTable(), np.zeros(1 << 16, np.int32)

    def _of_units(self, units) -> np.ndarray:
        import pyarrow as pa

        if len(self.table) + len(units) > self.most:
            self._reset()
        slot, h = self.table.find(units)
        n = np.where(slot >= 0, self.known[slot], -1)
        new = np.flatnonzero(slot < 0)
        if len(new):
            some = units.take(pa.array(new))
            n[new] = [self.fst.run_unit(w) for w in some.to_pylist()]
            at = self.table.add(some, h[new])
            while len(self.known) < len(self.table):
                self.known = np.concatenate([self.known, np.zeros_like(self.known)])
            self.known[at] = n[new]
        return n

    def __call__(self, texts: list[str]) -> np.ndarray:
        import pyarrow as pa
        import pyarrow.compute as pc

        out = np.zeros(len(texts), np.int64)
        plain, where = [], []
        for i, t in enumerate(texts):
            if not t:
                continue
            if BLANK in t:
                t = t.replace(BLANK, " ")
            if len(t) > self.chunk_chars or t[0] == " " or t[-1] == " " or "  " in t or (" \n" in t and not self.feed_resets):
                out[i] = self.fst.count(t, self.chunk_chars)
            else:
                # no piece holds a line feed, so it resets the transducer as well and begins a unit of its own
                plain.append(t.replace("\n", " \n") if self.feed_resets else t)
                where.append(i)
        if plain:
            cut = pc.split_pattern(pa.array(plain, pa.large_string()), " ")
            coded = cut.flatten().dictionary_encode()
            n = self._of_units(coded.dictionary)[coded.indices.to_numpy()]
            out[where] = np.add.reduceat(n.astype(np.int64), cut.offsets.to_numpy()[:-1])
        return out

