"""A bidirectional gated recurrent network with attention pooling, trained and run in numpy.

A window is a run of words. A word's input joins a hashed word vector and the mean of hashed character
n-gram vectors of the word with its borders. Two gated recurrent layers read the window in both
directions, attention weighs their joined states, and a logistic unit scores the pooled state.
"""

from __future__ import annotations

import re
import zlib

import numpy as np

WINDOW, STRIDE = 32, 16
WORD_CELLS, GRAM_CELLS, WORD_DIM, GRAM_DIM, HIDDEN, ATTEND = 4096, 16384, 8, 8, 8, 8
GRAMS = (3, 4)
#: Words are runs of letters and digits, or of marks other than full stops and commas; runs of over 40 are cut.
_WORD = re.compile(r"[^\W_]{1,40}|(?:[^\w\s.,]|_){1,40}")
F4 = np.float32


def text_words(text: str | None) -> list[str]:
    """The words of a text in lower case."""
    return _WORD.findall((text or "").lower())


def features(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word cell, n-gram cells, their number) of each word; n-grams are of UTF-8 bytes, borders included."""
    raw = [b"\x02" + w.encode("utf-8", "surrogatepass") + b"\x03" for w in words]
    n = np.array([len(r) for r in raw], np.int64)
    width = int(n.max(initial=4))
    m = np.zeros((len(raw), width), np.uint32)
    flat = np.frombuffer(b"".join(raw), np.uint8)
    rows = np.repeat(np.arange(len(raw)), n)
    m[rows, np.arange(len(flat)) - np.repeat(np.cumsum(n) - n, n)] = flat
    cells, valid = [], []
    for g in GRAMS:
        h = np.full((len(raw), width - g + 1), g, np.uint32)
        for j in range(g):
            h = (h ^ m[:, j : width - g + 1 + j]) * np.uint32(0x01000193) + np.uint32(0x9E3779B9)
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x85EBCA6B)
        cells.append((h >> np.uint32(18)).astype(np.int32))
        valid.append(np.arange(width - g + 1)[None] <= (n - g)[:, None])
    cell, ok = np.concatenate(cells, 1), np.concatenate(valid, 1)
    cell[~ok] = GRAM_CELLS  # an unused row of zeros
    word = np.array([zlib.crc32(r) % WORD_CELLS for r in raw], np.int64)
    return word, cell, ok.sum(1)


def _sigmoid(x):
    return 1.0 / (1.0 + np.exp(-x))


class Model:
    """Weights and both passes. Arrays are float32; `calibration` maps the best window's logit to a score."""

    def __init__(self, seed: int = 7):
        rng = np.random.default_rng(seed)
        d = WORD_DIM + GRAM_DIM

        def init(*shape, scale=None):
            return rng.normal(0, scale or 1 / np.sqrt(shape[0]), shape).astype(F4)

        self.w = {"Ew": init(WORD_CELLS, WORD_DIM, scale=0.1), "Eg": init(GRAM_CELLS + 1, GRAM_DIM, scale=0.3)}
        self.w["Eg"][GRAM_CELLS] = 0
        for side in "fb":
            self.w |= {f"W{side}": init(d, 3 * HIDDEN), f"U{side}": init(HIDDEN, 3 * HIDDEN), f"c{side}": np.zeros(3 * HIDDEN, F4)}
        self.w |= {"A": init(2 * HIDDEN, ATTEND), "v": init(ATTEND), "u": init(2 * HIDDEN), "b": np.zeros(1, F4)}
        self.calibration = (1.0, 0.0)

    # -- forward -------------------------------------------------------------------------------
    def inputs(self, word, cell, n) -> np.ndarray:
        return np.concatenate([self.w["Ew"][word], self.w["Eg"][cell].sum(1) / np.maximum(n, 1)[:, None].astype(F4)], 1)

    def project(self, x: np.ndarray) -> np.ndarray:
        """Gate inputs of both directions for each word type."""
        return np.concatenate([x @ self.w["Wf"] + self.w["cf"], x @ self.w["Wb"] + self.w["cb"]], 1).astype(F4)

    def forward(self, proj: np.ndarray, idx: np.ndarray, keep: bool = False):
        """Logits of windows; idx (windows, positions) points at rows of proj, -1 where a window is shorter."""
        n, t = idx.shape
        h2, hh = HIDDEN, 3 * HIDDEN
        states = np.zeros((t, n, 2 * h2), F4)
        full = idx >= 0
        saved: dict = {}
        for side, cols, steps in (("f", slice(0, hh), range(t)), ("b", slice(hh, 2 * hh), range(t - 1, -1, -1))):
            u = self.w[f"U{side}"]
            h = np.zeros((n, h2), F4)
            at = slice(0, h2) if side == "f" else slice(h2, 2 * h2)
            trace = []
            for s in steps:
                x = proj[idx[:, s], cols]
                g = h @ u
                rz = _sigmoid(x[:, : 2 * h2] + g[:, : 2 * h2])
                r, z = rz[:, :h2], rz[:, h2:]
                z = np.where(full[:, s, None], z, F4(1))
                c = np.tanh(x[:, 2 * h2 :] + r * g[:, 2 * h2 :])
                new = c + z * (h - c)
                if keep:
                    trace.append((s, h, r, z, c, g[:, 2 * h2 :]))
                h = new
                states[s, :, at] = h
            saved[side] = trace
        k = np.tanh(states @ self.w["A"])
        e = k @ self.w["v"]
        e[~full.T] = -30
        a = np.exp(e - e.max(0))
        a /= a.sum(0)
        pooled = np.einsum("tn,tnd->nd", a, states)
        logit = pooled @ self.w["u"] + self.w["b"]
        return (logit, (states, k, a, pooled, saved, full)) if keep else logit

    # -- training ------------------------------------------------------------------------------
    def gradients(self, feats, idx, y):
        """Loss and gradients of one batch; feats are the features of its word types."""
        w, h2, hh = self.w, HIDDEN, 3 * HIDDEN
        x = self.inputs(*feats)
        proj = self.project(x)
        logit, (states, k, a, pooled, saved, full) = self.forward(proj, idx, keep=True)
        p = _sigmoid(logit)
        loss = float(np.mean(np.maximum(logit, 0) - logit * y + np.log1p(np.exp(-np.abs(logit)))))
        dl = ((p - y) / len(y)).astype(F4)
        g = {"u": pooled.T @ dl, "b": dl.sum(keepdims=True)}
        dpool = dl[:, None] * w["u"]
        ds = a[:, :, None] * dpool[None]
        da = np.einsum("tnd,nd->tn", states, dpool)
        de = a * (da - (a * da).sum(0))
        g["v"] = np.einsum("tna,tn->a", k, de)
        dk = de[:, :, None] * w["v"] * (1 - k * k)
        g["A"] = np.einsum("tnd,tna->da", states, dk)
        ds += dk @ w["A"].T
        dproj = np.zeros_like(proj)
        for side in "fb":
            u = w[f"U{side}"]
            cols = slice(0, hh) if side == "f" else slice(hh, 2 * hh)
            at = slice(0, h2) if side == "f" else slice(h2, 2 * h2)
            gu, dh = np.zeros_like(u), np.zeros((idx.shape[0], h2), F4)
            for s, h, r, z, c, gc in reversed(saved[side]):
                dh = dh + ds[s, :, at]
                dc = dh * (1 - z) * (1 - c * c)
                dz = dh * (h - c) * z * (1 - z)
                dr = dc * gc * r * (1 - r)
                dx = np.concatenate([dr, dz, dc], 1)
                dg = np.concatenate([dr, dz, dc * r], 1)
                rows = full[:, s]
                dx[~rows] = 0
                dg[~rows] = 0
                np.add.at(dproj[:, cols], idx[rows, s], dx[rows])
                gu += h.T @ dg
                dh = dh * z + dg @ u.T
            g[f"U{side}"] = gu
            d = dproj[:, cols]
            g[f"W{side}"], g[f"c{side}"] = x.T @ d, d.sum(0)
        dx = dproj[:, :hh] @ w["Wf"].T + dproj[:, hh:] @ w["Wb"].T
        word, cell, n = feats
        g["Ew"], g["Eg"] = np.zeros_like(w["Ew"]), np.zeros_like(w["Eg"])
        np.add.at(g["Ew"], word, dx[:, :WORD_DIM])
        share = dx[:, WORD_DIM:] / np.maximum(n, 1)[:, None]
        np.add.at(g["Eg"], cell.ravel(), np.repeat(share, cell.shape[1], 0))
        g["Eg"][GRAM_CELLS] = 0
        return loss, g

    def fit(self, windows: list[list[str]], y: np.ndarray, epochs: int, rate: float = 0.01, batch: int = 256, seed: int = 3) -> None:
        rng = np.random.default_rng(seed)
        if not hasattr(self, "_m"):
            self._m = {k: np.zeros_like(v) for k, v in self.w.items()}
            self._v = {k: np.zeros_like(v) for k, v in self.w.items()}
            self._t = 0
        for _ in range(epochs):
            order = rng.permutation(len(windows))
            for lo in range(0, len(order), batch):
                part = order[lo : lo + batch]
                table, idx = index_windows([windows[i] for i in part])
                _, g = self.gradients(features(table), idx, y[part].astype(F4))
                self._t += 1
                lr = rate * np.sqrt(1 - 0.999**self._t) / (1 - 0.9**self._t)
                for k, d in g.items():
                    m, v = self._m[k], self._v[k]
                    m += 0.1 * (d - m)
                    v += 0.001 * (d * d - v)
                    self.w[k] -= (lr * m / (np.sqrt(v) + 1e-8)).astype(F4)

    # -- scoring -------------------------------------------------------------------------------
    def score_of(self, logit: np.ndarray) -> np.ndarray:
        a, b = self.calibration
        return 1.0 / (1.0 + np.exp(-np.clip(a * np.asarray(logit, np.float64) + b, -500, 500)))


def spans(n: int) -> list[tuple[int, int]]:
    """Word ranges of the overlapping windows of a text of n words; together they cover every word twice (but the ends)."""
    return [(s, min(s + WINDOW, n)) for s in range(0, max(1, n - STRIDE), STRIDE)] if n else []


def index_windows(windows: list[list[str]]) -> tuple[list[str], np.ndarray]:
    table: dict[str, int] = {}
    idx = np.full((len(windows), WINDOW), -1, np.int64)
    for i, w in enumerate(windows):
        idx[i, : len(w)] = [table.setdefault(x, len(table)) for x in w]
    return list(table), idx


class Scorer:
    """Scores whole texts; gate inputs of word types are kept in a table of bounded size."""

    def __init__(self, model: Model, most: int = 150_000, at_once: int = 3000):
        self.model, self.most, self.at_once = model, most, at_once
        self._reset()

    def _reset(self):
        self.at: dict[str, int] = {}
        self.table = np.zeros((4096, 6 * HIDDEN), F4)

    def _learn(self, new: list[str]) -> None:
        for lo in range(0, len(new), 8000):
            part = sorted(new[lo : lo + 8000], key=len)
            for q in range(0, len(part), 1000):
                few = part[q : q + 1000]
                rows = self.model.project(self.model.inputs(*features(few)))
                need = len(self.at) + len(few)
                while need > len(self.table):
                    self.table = np.concatenate([self.table, np.zeros_like(self.table)])
                self.table[len(self.at) : need] = rows
                self.at.update(zip(few, range(len(self.at), need)))

    def logits(self, texts: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """(best window logit, its index) of each text; -inf and -1 for texts without words."""
        best, where = np.full(len(texts), -np.inf), np.full(len(texts), -1)
        new = set().union(*texts).difference(self.at) if texts else set()
        if len(self.at) + len(new) > self.most:
            self._reset()
            new = set().union(*texts)
        self._learn(list(new))
        get = self.at.__getitem__
        owner, number, rows = [], [], []
        for i, t in enumerate(texts):
            if t:
                ids = np.fromiter(map(get, t), np.int64, len(t))
                count = len(spans(len(t)))
                pad = np.full((count - 1) * STRIDE + WINDOW, -1, np.int64)
                pad[: len(ids)] = ids
                rows.append(np.lib.stride_tricks.sliding_window_view(pad, WINDOW)[::STRIDE])
                owner += [i] * count
                number += range(count)
        if rows:
            idx = np.concatenate(rows)
            logit = np.concatenate([self.model.forward(self.table, idx[lo : lo + self.at_once]) for lo in range(0, len(idx), self.at_once)])
            owner, number = np.array(owner), np.array(number)
            order = np.lexsort((number, -logit, owner))
            first = order[np.append(True, owner[order][1:] != owner[order][:-1])]
            best[owner[first]], where[owner[first]] = logit[first], number[first]
        return best, where


def train(texts: list[str | None], labels: list[int], seed: int = 7, epochs: int = 6, rounds: int = 2) -> Model | None:
    """Fit on whole labelled texts; None if only one class has texts with words.

    Which window makes a text toxic is not labelled. The first windows come from document-frequency
    odds of words and n-grams; then each round takes the windows that the model itself scores highest,
    toxic texts' as positive and clean texts' as hard negatives.
    """
    words = [text_words(t) for t in texts]
    y = np.array(labels)
    rng = np.random.default_rng(seed)
    kept = [i for i in range(len(words)) if words[i]]
    if len({int(y[i]) for i in kept}) < 2:
        return None
    n1, n0 = max(1, sum(y[i] for i in kept)), max(1, sum(1 - y[i] for i in kept))
    seen: dict[str, list[int]] = {}
    for i in kept:
        for key in {k for w in set(words[i]) for k in _keys(w)}:
            seen.setdefault(key, [0, 0])[y[i]] += 1
    odds = {k: np.log((c[1] + 0.5) / (n1 + 1)) - np.log((c[0] + 0.5) / (n0 + 1)) - 2.0 / np.sqrt(c[1] + 1) for k, c in seen.items() if c[1] > 1}
    del seen
    worth: dict[str, float] = {}

    def value(w: str) -> float:
        v = worth.get(w)
        if v is None:
            v = worth[w] = max((odds.get(k, -9.0) for k in _keys(w)), default=-9.0)
        return v

    def top(i: int) -> list[str]:
        return max((words[i][a:b] for a, b in spans(len(words[i]))), key=lambda win: max(map(value, win)))

    def some(i: int) -> list[str]:
        parts = spans(len(words[i]))
        a, b = parts[rng.integers(len(parts))]
        return words[i][a:b]

    model = Model(seed)
    good, bad = [i for i in kept if y[i] == 0], [i for i in kept if y[i] == 1]
    pick = [top(i) for i in bad] + [top(i) for i in good] + [some(i) for i in good]
    target = np.array([1] * len(bad) + [0] * (2 * len(good)))
    model.fit(pick, target, epochs, seed=seed)
    for r in range(rounds):
        scorer = Scorer(model)
        hard = []
        for lo in range(0, len(kept), 200):
            part = kept[lo : lo + 200]
            _, where = scorer.logits([words[i] for i in part])
            hard += [words[i][slice(*spans(len(words[i]))[j])] for i, j in zip(part, where.tolist())]
        pick = hard + [some(i) for i in good]
        target = np.array([y[i] for i in kept] + [0] * len(good))
        model.fit(pick, target, max(2, epochs // 2), rate=0.005 / (r + 1), seed=seed + r + 1)
    scorer, best = Scorer(model), []
    for lo in range(0, len(kept), 200):
        best += scorer.logits([words[i] for i in kept[lo : lo + 200]])[0].tolist()
    model.calibration = _calibrate(np.array(best), y[kept].astype(float))
    for extra in ("_m", "_v", "_t"):
        delattr(model, extra)
    return model


def _keys(w: str) -> list[str]:
    """Evidence units for the first windows: the word and its character 4- and 5-grams at the beginning."""
    return ["=" + w, *("^" + w[:n] for n in (4, 5, 6) if len(w) > n)]


def _calibrate(logit: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Logistic regression of the label on the best window's logit, with smoothed targets."""
    t = np.where(y > 0, (y.sum() + 1) / (y.sum() + 2), 1 / ((1 - y).sum() + 2))
    a, b = 1.0, 0.0
    for _ in range(200):
        p = 1 / (1 + np.exp(-np.clip(a * logit + b, -50, 50)))
        w = np.maximum(p * (1 - p), 1e-6)
        ga, gb = ((p - t) * logit).sum() + 1e-3 * (a - 1), (p - t).sum()
        haa, hab, hbb = (w * logit * logit).sum() + 1e-3, (w * logit).sum(), w.sum()
        det = haa * hbb - hab * hab
        if det <= 1e-12:
            break
        da, db = (hbb * ga - hab * gb) / det, (haa * gb - hab * ga) / det
        step = min(1.0, 2.0 / max(abs(da), abs(db), 1e-9))
        a, b = a - step * da, b - step * db
        if max(abs(da), abs(db)) < 1e-7:
            break
    return (float(max(a, 0.05)), float(b))
