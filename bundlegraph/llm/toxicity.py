"""Toxicity: a bidirectional gated recurrent network with attention pooling, in numpy.

A token's input joins word and character inputs: a learned embedding of the word (by hash), the mean
of learned embeddings of its character n-grams (by hash), and six figures: log-odds of the word in
toxic against clean documents, is it known, length, largest and mean log-odds of its n-grams, share of
capitals. A text is cut into overlapping windows of `WINDOW` words, every `STRIDE` words one;
each is read in both directions, pooled by attention and scored. A text's score is that of its
worst window, so one insult in a long text counts.

Only documents have labels, so training picks windows: first by the log-odds alone, later by
the network's own scores. It reads at most about `sample` labelled documents of each class, none
over `longest` characters, which bounds what the driver holds; scoring reads whole texts.

Nulls: null and blank texts score 0. Null labels are not learned from; a document with several
labels counts as toxic if one says so. Without labels of both classes every score is 0. Repeated
rows score alike, empty tables give no rows, other columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from array import array
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fitted, take_over, trim
from .langid import fold

WINDOW, STRIDE, HIDDEN, ATTEND = 32, 16, 8, 8
FIGURES, WORD_DIM, GRAM_DIM = 6, 8, 8
INPUTS = FIGURES + WORD_DIM + GRAM_DIM
WORD_ROWS, GRAM_ROWS = 4096, 8192  # rows of the embeddings; words and n-grams share them by hash
_EDGE = ".,;:!?\"'()[]{}|*&%$#~`<>-_/\\+=^@"


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


class Inputs:
    """Word and character log-odds, from sets of words of labelled documents."""

    def __init__(self, words: dict[str, float], grams: dict[str, float]):
        self.words, self.grams = words, grams
        self._table: _Odds | None = None

    def __getstate__(self):
        return self.__dict__ | {"_table": None}

    @property
    def table(self) -> "_Odds":
        if self._table is None:
            self._table = _Odds(self.grams)
        return self._table

    @staticmethod
    def parts(w: str) -> list[str]:
        m = f"^{w}$"
        return [m[i : i + n] for n in (4, 5) for i in range(len(m) - n + 1)]

    @classmethod
    def fit(cls, docs: list[tuple[set[str], int, int]], folds: int, least: int = 4) -> list["Inputs"]:
        """docs: words, label, fold. Odds without each fold in turn, then those of all documents."""
        n = Counter((f, y) for _, y, f in docs)
        words, grams = defaultdict(Counter), defaultdict(Counter)
        one = {}.setdefault  # equal strings are held once
        for found, y, f in docs:
            words[f, y].update(found)
            grams[f, y].update({one(g, g) for w in found for g in cls.parts(w)})
        one = None
        smooth = 3.0  # keeps what few documents hold near zero

        def odds(table: dict, out: int) -> dict[str, float]:
            seen = [Counter(), Counter()]
            size = [0, 0]
            for y in (0, 1):
                for f in range(folds):
                    if f != out:
                        seen[y].update(table[f, y])
                        size[y] += n[f, y]
            clean, toxic = seen
            base = math.log((size[0] + 2 * smooth) / (size[1] + 2 * smooth))
            return {k: math.log((toxic[k] + smooth) / (clean[k] + smooth)) + base for k in clean.keys() | toxic.keys() if clean[k] + toxic[k] >= least}

        del docs
        rare = Counter()
        for c in grams.values():
            rare.update(c)
        for c in grams.values():  # n-grams of few documents get no odds in any case
            for k in [k for k in c if rare[k] < least]:
                del c[k]
        rare.clear()
        return [cls(odds(words, f), {k: v for k, v in odds(grams, f).items() if abs(v) > 0.2}) for f in range(folds + 1)]

    def of(self, tokens: list[str]) -> tuple[np.ndarray, list[int], np.ndarray, np.ndarray]:
        """For each token the six figures, the row of the word's embedding and how many n-grams it has; the
        rows of their embeddings, token by token."""
        bare = [t.lower().strip(_EDGE) for t in tokens]
        many, high, low, rows = _grams(bare)
        got, some = self.table.of(high, low), many > 0
        known = [self.words.get(w) for w in bare]
        figures = np.zeros((len(bare), FIGURES))
        figures[:, 0] = [(k or 0.0) / 2 for k in known]
        figures[:, 1] = [k is not None for k in known]
        figures[:, 2] = [min(len(w), 20) / 10 for w in bare]
        if len(got):
            at = (np.cumsum(many) - many)[some]
            figures[some, 3] = np.maximum.reduceat(got, at) / 2
            figures[some, 4] = np.add.reduceat(got, at) / many[some]
        figures[:, 5] = [0.0 if t.islower() else sum(map(str.isupper, t)) / len(t) for t in tokens]
        words = [zlib.crc32(w.encode("utf-8", "surrogatepass")) % WORD_ROWS for w in bare]
        return figures.astype(np.float32), words, many, rows


# a checksum is the exclusive or of one part for each byte, by how many bytes follow it, and one for the length
_BYTE = np.array([[(zlib.crc32(bytes([b]) + bytes(k)) ^ zlib.crc32(bytes(k + 1))) % GRAM_ROWS for b in range(256)] for k in range(20)], dtype=np.uint16)
_LENGTH = [zlib.crc32(bytes(k)) % GRAM_ROWS for k in range(21)]


def _grams(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """All n-grams of `Inputs.parts`, word by word, without a string for each: how many each word has, their
    characters in two numbers (three in one, two in the other) and crc32 % GRAM_ROWS."""
    text = "".join([f"^{w}$" for w in words])
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), dtype=np.uint8)
    char = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.uint64)
    byte = np.append(np.flatnonzero((raw & 0xC0) != 0x80), len(raw))
    size = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    start, fours, fives = np.cumsum(size + 2) - size - 2, np.maximum(size - 1, 0), np.maximum(size - 2, 0)
    many = fours + fives
    first = np.cumsum(many) - many
    high, low, rows = np.empty(many.sum(), dtype=np.uint64), np.empty(many.sum(), dtype=np.uint64), np.empty(many.sum(), dtype=np.int32)
    three = char[:-2] | char[1:-1] << np.uint64(21) | char[2:] << np.uint64(42) if len(char) > 2 else char[:0]
    for n, count, to in ((4, fours, first), (5, fives, first + fours)):
        nth = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        at, to = np.repeat(start, count) + nth, np.repeat(to, count) + nth
        high[to] = three[at]
        low[to] = char[at + 3] if n == 4 else char[at + 3] | (char[at + 4] + np.uint64(1)) << np.uint64(21)
        begin = byte[at]
        length = byte[at + n] - begin
        for k in np.flatnonzero(np.bincount(length)).tolist():
            of = length == k
            b, row = begin[of], np.full(int(of.sum()), _LENGTH[k], dtype=np.uint16)
            for j in range(k):
                row ^= _BYTE[k - 1 - j][raw[b + j]]
            rows[to[of]] = row
    return many, high, low, rows


class _Odds:
    """Log-odds of n-grams by the numbers of `_grams`: open addressing, whole keys are compared."""

    def __init__(self, odds: dict[str, float]):
        char = [[ord(c) for c in g] for g in odds]
        high = np.array([c[0] | c[1] << 21 | c[2] << 42 for c in char], dtype=np.uint64)
        low = np.array([c[3] | (c[4] + 1 << 21 if len(c) == 5 else 0) for c in char], dtype=np.uint64)
        self.bits = max(4, (4 * len(odds)).bit_length())
        self.slot = np.full(1 << self.bits, -1, dtype=np.int32)
        left, at = np.arange(len(odds), dtype=np.int32), self._at(high, low)
        while len(left):  # a slot goes to one of those who ask for it, the others try the next
            free = self.slot[at] < 0
            self.slot[at[free]] = left[free]
            again = self.slot[at] != left
            left, at = left[again], at[again] + 1 & len(self.slot) - 1
        self.high, self.low, self.odds = high, low, np.array(list(odds.values()), dtype=np.float64)

    def _at(self, high: np.ndarray, low: np.ndarray) -> np.ndarray:
        mixed = high * np.uint64(0x9E3779B97F4A7C15) ^ low * np.uint64(0xC2B2AE3D27D4EB4F)
        return ((mixed ^ mixed >> np.uint64(29)) * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(64 - self.bits)).astype(np.int64)

    def of(self, high: np.ndarray, low: np.ndarray) -> np.ndarray:
        """The odds of each n-gram, 0 where it has none."""
        out, left, at = np.zeros(len(high)), np.arange(len(high)), self._at(high, low)
        while len(left):
            held = self.slot[at]
            some = held >= 0
            left, at, held = left[some], at[some], held[some]
            same = (self.high[held] == high[left]) & (self.low[held] == low[left])
            out[left[same]] = self.odds[held[same]]
            left, at = left[~same], at[~same] + 1 & len(self.slot) - 1
        return out


class Tokens:
    """Types of tokens in flat arrays; type 0 stands for no token."""

    def __init__(self):
        self._figures, self._word, self._many, self._grams = array("f", [0.0] * FIGURES), array("i", [0]), array("i", [0]), array("i")

    def add(self, inputs: Inputs, token: str) -> int:
        """The number of a new type."""
        return self.extend(inputs, [token]) - 1

    def extend(self, inputs: Inputs, tokens: list[str]) -> int:
        """New types, numbered in their order; how many types there are then, with type 0."""
        figures, words, many, rows = inputs.of(tokens)
        self._figures.frombytes(figures.tobytes())
        self._word.extend(words)
        self._many.frombytes(many.astype(np.int32).tobytes())
        self._grams.frombytes(rows.tobytes())
        return len(self._word)

    def done(self) -> "Tokens":
        """No more types come: the arrays as numpy's, without a copy."""
        self.figures = np.frombuffer(self._figures, dtype=np.float32).reshape(-1, FIGURES)
        self.word, self.many = np.frombuffer(self._word, dtype=np.int32), np.frombuffer(self._many, dtype=np.int32)
        self.grams = np.frombuffer(self._grams, dtype=np.int32)
        self.at = np.cumsum(self.many, dtype=np.int64) - self.many
        return self

    def gram_rows(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Embedding rows of the n-grams of some types, and which of these types each belongs to."""
        n = self.many[ids]
        owner = np.repeat(np.arange(len(ids)), n)
        return self.grams[np.repeat(self.at[ids], n) + np.arange(len(owner)) - np.repeat(np.cumsum(n) - n, n)], owner


class Network:
    def __init__(self, seed: int = 7):
        rng = np.random.default_rng(seed)
        d, h, a = INPUTS, HIDDEN, ATTEND
        n = lambda *s: (rng.normal(size=s) / math.sqrt(s[0])).astype(np.float32)
        z = lambda *s: np.zeros(s, dtype=np.float32)
        self.e = {"word": (rng.normal(size=(WORD_ROWS, WORD_DIM)) / 20).astype(np.float32), "gram": (rng.normal(size=(GRAM_ROWS, GRAM_DIM)) / 20).astype(np.float32)}
        self.p = {"Wf": n(d, 3 * h), "Uf": n(h, 3 * h), "bf": z(3 * h), "Wb": n(d, 3 * h), "Ub": n(h, 3 * h), "bb": z(3 * h), "Wa": n(2 * h, a), "ba": z(a), "va": n(a), "wo": n(2 * h), "bo": z(1)}

    def inputs(self, tokens: Tokens, ids: np.ndarray) -> np.ndarray:
        """Input rows of some types."""
        rows, owner = tokens.gram_rows(ids)
        mean = np.zeros((len(ids), GRAM_DIM), dtype=np.float32)
        for k in range(GRAM_DIM):
            mean[:, k] = np.bincount(owner, weights=self.e["gram"][rows, k], minlength=len(ids))
        mean /= np.maximum(tokens.many[ids], 1)[:, None]
        word = np.where(tokens.many[ids][:, None] > 0, self.e["word"][tokens.word[ids]], 0)
        return np.concatenate([tokens.figures[ids], word, mean], axis=1).astype(np.float32)

    def embedding_gradients(self, tokens: Tokens, ids: np.ndarray, dx: np.ndarray) -> dict[str, np.ndarray]:
        """From gradients of the input rows of some (distinct) types."""
        g = {k: np.zeros_like(v) for k, v in self.e.items()}
        some = tokens.many[ids] > 0
        np.add.at(g["word"], tokens.word[ids[some]], dx[some, FIGURES : FIGURES + WORD_DIM])
        rows, owner = tokens.gram_rows(ids)
        share = dx[:, FIGURES + WORD_DIM :] / np.maximum(tokens.many[ids], 1)[:, None]
        for k in range(GRAM_DIM):
            g["gram"][:, k] = np.bincount(rows, weights=share[owner, k], minlength=GRAM_ROWS)
        return g

    def project(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Input part of the gates of both directions; depends on the token alone."""
        return x @ self.p["Wf"] + self.p["bf"], x @ self.p["Wb"] + self.p["bb"]

    def read(self, gates, u: np.ndarray, n: int, steps, keep: bool):
        """gates(t): n x 3H input parts. Hidden states by step, and what backpropagation needs."""
        h, hs, held = np.zeros((n, HIDDEN), dtype=u.dtype), {}, {}
        k = 2 * HIDDEN
        for t in steps:
            x, g = gates(t), h @ u
            rz = _sigmoid(x[:, :k] + g[:, :k])
            r, zt = rz[:, :HIDDEN], rz[:, HIDDEN:]
            c = np.tanh(x[:, k:] + r * g[:, k:])
            if keep:
                held[t] = (h, r, zt, c, g[:, k:])
            h = c + zt * (h - c)
            hs[t] = h
        return hs, held

    def forward(self, gf, gb, mask: np.ndarray, keep: bool = False):
        n, w = mask.shape
        p = self.p
        f, kf = self.read(gf, p["Uf"], n, range(w), keep)
        b, kb = self.read(gb, p["Ub"], n, range(w - 1, -1, -1), keep)
        hid = np.empty((n, w, 2 * HIDDEN), dtype=p["Uf"].dtype)
        for t in range(w):
            hid[:, t, :HIDDEN], hid[:, t, HIDDEN:] = f[t], b[t]
        e = np.tanh(hid @ p["Wa"] + p["ba"])
        s = np.where(mask, e @ p["va"], -1e9)
        s = np.exp(s - s.max(axis=1, keepdims=True))
        att = s / s.sum(axis=1, keepdims=True)
        pooled = np.einsum("nt,nth->nh", att, hid)
        logit = pooled @ p["wo"] + p["bo"][0]
        return (logit, hid, e, att, pooled, kf, kb) if keep else logit

    def gradients(self, x: np.ndarray, mask: np.ndarray, y: np.ndarray, weight: np.ndarray):
        """Mean weighted logistic loss of windows x (n x w x inputs), its gradients, and those of x."""
        p, n = self.p, len(x)
        xf, xb = self.project(x)
        logit, hid, e, att, pooled, kf, kb = self.forward(lambda t: xf[:, t], lambda t: xb[:, t], mask, keep=True)
        loss = float((weight * (np.logaddexp(0, logit) - y * logit)).mean())
        d = ((_sigmoid(logit) - y) * weight / n).astype(x.dtype)
        g = {"wo": pooled.T @ d, "bo": np.array([d.sum()], dtype=x.dtype)}
        dpool = d[:, None] * p["wo"]
        datt = np.einsum("nh,nth->nt", dpool, hid)
        dhid = att[:, :, None] * dpool[:, None, :]
        ds = att * (datt - (att * datt).sum(axis=1, keepdims=True))
        g["va"] = np.einsum("nt,nta->a", ds, e)
        de = ds[:, :, None] * p["va"] * (1 - e * e)
        g["Wa"], g["ba"] = np.einsum("nth,nta->ha", hid, de), de.sum(axis=(0, 1))
        dhid += de @ p["Wa"].T
        din = np.zeros_like(x)
        for side, held, steps, cut in (("f", kf, range(x.shape[1] - 1, -1, -1), slice(0, HIDDEN)), ("b", kb, range(x.shape[1]), slice(HIDDEN, None))):
            u = p["U" + side]
            du, dw, db = np.zeros_like(u), np.zeros_like(p["W" + side]), np.zeros_like(p["b" + side])
            back = p["W" + side].T
            dh = np.zeros((n, HIDDEN), dtype=x.dtype)
            for t in steps:
                h0, r, zt, c, gc = held[t]
                dh = dh + dhid[:, t, cut]
                dc = dh * (1 - zt) * (1 - c * c)
                dz = dh * (h0 - c) * zt * (1 - zt)
                dr = dc * gc * r * (1 - r)
                dx, dg = np.concatenate([dr, dz, dc], axis=1), np.concatenate([dr, dz, dc * r], axis=1)
                du += h0.T @ dg
                dw += x[:, t].T @ dx
                db += dx.sum(axis=0)
                din[:, t] += dx @ back
                dh = dh * zt + dg @ u.T
            g["U" + side], g["W" + side], g["b" + side] = du, dw, db
        return loss, g, din

    def train(self, tokens: Tokens, ids: np.ndarray, mask: np.ndarray, y: np.ndarray, steps: int, rng, rate: float = 0.01, batch: int = 128, decay: float = 2e-3, drop: float = 0.3) -> float:
        """Adam on windows of token types; the embeddings learn along and are drawn towards zero."""
        weight = np.where(y == 1, len(y) / max(1, 2 * y.sum()), len(y) / max(1, 2 * (1 - y).sum())).astype(np.float32)
        learned = self.p | self.e
        m = {k: np.zeros_like(v) for k, v in learned.items()}
        v = {k: np.zeros_like(v) for k, v in learned.items()}
        loss, order, at = 0.0, rng.permutation(len(y)), 0
        for step in range(1, steps + 1):
            part, at = order[at : at + batch], at + batch
            if at >= len(y):
                order, at = rng.permutation(len(y)), 0
            types, where = np.unique(ids[part], return_inverse=True)
            where = where.reshape(ids[part].shape)
            x, bare = self.inputs(tokens, types), rng.random(len(types)) < drop
            x[bare, FIGURES:] = 0  # some words go without embeddings, so none is relied on alone
            loss, g, din = self.gradients(x[where], mask[part], y[part].astype(np.float32), weight[part])
            dx = np.zeros((len(types), INPUTS), dtype=np.float32)
            np.add.at(dx, where[mask[part]], din[mask[part]])
            dx[bare] = 0
            g |= self.embedding_gradients(tokens, types, dx)
            for k, w in learned.items():
                if k in self.e:
                    g[k] += decay * w / len(y)
                m[k] = 0.9 * m[k] + 0.1 * g[k]
                v[k] = 0.99 * v[k] + 0.01 * g[k] * g[k]
                w -= (rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-7)).astype(np.float32)
        return loss


def windows(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, first token and length of every overlapping window, for documents laid end to end."""
    n = np.maximum(1, -(-(lengths - WINDOW) // STRIDE) + 1)
    doc = np.repeat(np.arange(len(lengths)), n)
    nth = np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)
    base = np.cumsum(lengths) - lengths
    start = nth * STRIDE
    return doc, base[doc] + start, np.minimum(WINDOW, lengths[doc] - start)


class _Types(dict):
    """Tokens to rows of a growing table of projected inputs; row 0 stands for no token."""

    def __init__(self, model: "ToxicityModel"):
        self.model = model
        self.fresh: list[str] = []

    def __missing__(self, token: str) -> int:
        self.fresh.append(token)
        i = self[token] = len(self) + 1
        return i


class ToxicityModel:
    """Inputs and network; `lift` moves the decision to 0.5."""

    def __init__(self, inputs: Inputs | None, net: Network | None, room: int = 300_000):
        self.inputs, self.net, self.lift, self.room = inputs, net, 0.0, room
        self.types: _Types | None = None

    def __getstate__(self):
        return self.__dict__ | {"types": None, "gf": None, "gb": None}

    def forget(self) -> None:
        self.types = self.gf = self.gb = None

    def _reset(self) -> None:
        self.types = _Types(self)
        gf, gb = self.net.project(np.zeros((1, INPUTS), dtype=np.float32))
        self.gf, self.gb, self.filled = np.repeat(gf, 4096, axis=0), np.repeat(gb, 4096, axis=0), 1

    def _grow(self) -> None:
        fresh = self.types.fresh
        if not fresh:
            return
        need = self.filled + len(fresh)
        if need > len(self.gf):
            more = max(need, 2 * len(self.gf)) - len(self.gf)
            self.gf, self.gb = (np.concatenate([g, np.zeros((more, 3 * HIDDEN), dtype=np.float32)]) for g in (self.gf, self.gb))
        cuts = (np.flatnonzero(np.diff(np.cumsum([len(t) for t in fresh]) >> 17)) + 1).tolist()  # about 131,072 characters at once
        for lo, hi in zip([0, *cuts], [*cuts, len(fresh)]):
            new = Tokens()
            new.extend(self.inputs, fresh[lo:hi])
            to = slice(self.filled, self.filled + hi - lo)
            self.gf[to], self.gb[to] = self.net.project(self.net.inputs(new.done(), np.arange(1, hi - lo + 1)))
            self.filled = to.stop
        fresh.clear()

    def window_logits(self, tokens: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """Document of each window, and its logit."""
        if self.types is None or len(self.types) > self.room:
            self._reset()
        lengths = np.array([len(t) for t in tokens], dtype=np.int64)
        flat = np.fromiter(map(self.types.__getitem__, chain.from_iterable(tokens)), dtype=np.int64, count=int(lengths.sum()))
        self._grow()
        flat = np.append(flat, 0)
        doc, start, size = windows(lengths)
        out = np.empty(len(doc), dtype=np.float32)
        for lo in range(0, len(doc), 8192):
            part = slice(lo, lo + 8192)
            mask = np.arange(WINDOW) < size[part, None]
            ids = np.where(mask, flat[np.minimum(start[part, None] + np.arange(WINDOW), len(flat) - 1)], 0).T.copy()
            out[part] = self.net.forward(lambda t: self.gf[ids[t]], lambda t: self.gb[ids[t]], mask)
        return doc, out

    def scores(self, texts: list[str | None]) -> np.ndarray:
        """One score for each text, 0 to 1."""
        out = np.zeros(len(texts))
        if self.net is None:
            return out
        held, at, total = [], [], 0
        for i, t in enumerate(texts):
            words = t.split() if t else []
            if words:
                held.append(words)
                at.append(i)
                total += len(words)
            if held and (total > 120_000 or i == len(texts) - 1):
                doc, logit = self.window_logits(held)
                worst = np.maximum.reduceat(logit, np.flatnonzero(np.r_[True, np.diff(doc) > 0]))
                out[at] = _sigmoid(worst.astype(np.float64) + self.lift)
                held, at, total = [], [], 0
        if held:
            doc, logit = self.window_logits(held)
            out[at] = _sigmoid(np.maximum.reduceat(logit, np.flatnonzero(np.r_[True, np.diff(doc) > 0])).astype(np.float64) + self.lift)
        return out


def fit_network(texts: list[str], labels: list[int], rounds: int = 3, steps: int = 300, folds: int = 4) -> ToxicityModel:
    """Train on whole labelled texts; equal texts count once.

    A document's inputs in training come from odds that did not see its fold, as will be so for
    new documents. The fold is a minhash of the words, so near copies mostly share one.
    """
    uniq = {t: y for t, y in zip(texts, labels) if t and t.split()}
    one = {}.setdefault  # equal strings are held once
    tokens, y = [[one(w, w) for w in t.split()] for t in uniq], np.array(list(uniq.values()))
    if len(set(y.tolist())) < 2:
        return ToxicityModel(None, None)
    bare = [{one(b, b) for b in (w.lower().strip(_EDGE) for w in t)} - {""} for t in tokens]
    fold_of = [min((zlib.crc32(w.encode()) for w in b), default=0) % folds for b in bare]
    *without, inputs = Inputs.fit(list(zip(bare, y.tolist(), fold_of)), folds)
    del bare, uniq, one
    model, rng = ToxicityModel(inputs, Network()), np.random.default_rng(11)
    lengths = np.array([len(t) for t in tokens], dtype=np.int64)
    doc, start, size = windows(lengths)
    seen: list[dict[str, int]] = [{} for _ in range(folds)]
    kinds, flat = Tokens(), array("i")
    for t, f in zip(tokens, fold_of):
        known = seen[f]
        fresh = [w for w in dict.fromkeys(t) if w not in known]
        n = kinds.extend(without[f], fresh)
        known.update(zip(fresh, range(n - len(fresh), n)))
        flat.extend(map(known.__getitem__, t))
    kinds.done()
    flat.append(0)
    flat = np.frombuffer(flat, dtype=np.int32)
    del seen, without, tokens

    def ids(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        mask = np.arange(WINDOW) < size[rows, None]
        return np.where(mask, flat[np.minimum(start[rows, None] + np.arange(WINDOW), len(flat) - 1)], 0), mask

    def all_logits() -> np.ndarray:
        every = np.arange(len(kinds.word))
        gates = [model.net.project(model.net.inputs(kinds, every[lo : lo + 16_384])) for lo in range(0, len(every), 16_384)]
        gf, gb = (np.concatenate(g) for g in zip(*gates))
        del gates
        out = np.empty(len(doc), dtype=np.float32)
        for lo in range(0, len(doc), 8192):
            at, mask = ids(np.arange(lo, min(lo + 8192, len(doc))))
            out[lo : lo + len(at)] = model.net.forward(lambda t: gf[at[:, t]], lambda t: gb[at[:, t]], mask)
        return out

    hint = np.maximum(kinds.figures[:, 0], kinds.figures[:, 3])
    logit = np.concatenate([hint[ids(np.arange(lo, min(lo + 8192, len(doc))))[0]].max(axis=1) for lo in range(0, len(doc), 8192)])
    first = np.flatnonzero(np.r_[True, np.diff(doc) > 0])
    # one fold is kept from the network and sets the threshold, if it and the others have both classes
    spared = np.array(fold_of) == 0
    if len(set(y[spared].tolist())) < 2 or len(set(y[~spared].tolist())) < 2:
        spared[:] = False
    for k in range(rounds):
        order = np.lexsort((-logit, doc))  # the worst window of each document comes first
        extra = rng.choice(len(doc), size=min(len(doc), 2 * len(first)), replace=False)
        picked = np.unique(np.concatenate([order[first], extra[y[doc[extra]] == 0]]))
        picked = picked[~spared[doc[picked]]]
        at, mask = ids(picked)
        model.net.train(kinds, at, mask, y[doc[picked]], steps if k == 0 else steps // 2, rng, rate=0.01 if k == 0 else 0.004)
        logit = all_logits()
    top = np.maximum.reduceat(logit, first)
    if spared.any():
        top, y = top[spared], y[spared]
    pos, neg = np.sort(top[y == 1]), np.sort(top[y == 0])
    cuts = np.unique(np.concatenate([pos, neg]))
    mids = np.concatenate([[cuts[0] - 1], (cuts[1:] + cuts[:-1]) / 2, [cuts[-1] + 1]])
    wrong = np.searchsorted(pos, mids) / len(pos) + (len(neg) - np.searchsorted(neg, mids)) / len(neg)
    best = np.flatnonzero(wrong <= wrong.min() + 1e-12)
    model.lift = -float(mids[best[len(best) // 2]])
    return model


def fit_toxicity(docs: DataFrame, labels: DataFrame, sample: int = 800, longest: int = 50_000) -> ToxicityModel:
    """Fit on about `sample` labelled documents of each class, chosen by a hash of doc_id."""
    trim()
    known = labels.where("toxic IS NOT NULL AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    counts = {r.toxic: r["count"] for r in known.where("toxic IN (0, 1)").groupBy("toxic").count().collect()}
    room = 1 << 30
    share = F.when(F.col("toxic") == 1, int(min(1.0, sample / max(1, counts.get(1, 0))) * room)).otherwise(int(min(1.0, sample / max(1, counts.get(0, 0))) * room))
    picked = known.where("toxic IN (0, 1)").where(F.pmod(F.xxhash64("doc_id", F.lit("tox")), F.lit(room)) < share)
    # bounded by `sample`, so it may be broadcast
    got = docs.select("doc_id", "text").where(F.length("text") <= longest).join(F.broadcast(picked), "doc_id").select("doc_id", "text", "toxic")

    def fit(t: pa.Table) -> ToxicityModel:
        rows = sorted(zip(t["doc_id"].to_pylist(), t["text"].to_pylist(), t["toxic"].to_pylist()))
        return fit_network([r[1] for r in rows], [int(r[2]) for r in rows])

    return fitted(got, fit)


def score_toxicity(docs: DataFrame, model: ToxicityModel, keep: list[str] | None = None, name: str = "score") -> DataFrame:
    """The columns of `keep` (doc_id if not given) and a score of the whole text."""
    trim()
    kept = keep or ["doc_id"]
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the sample of the fit
    at = kept.index("text") if "text" in kept else len(kept)
    fields = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in kept)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("toxicity", shared.value.forget)
        for b in batches:
            for lo in range(0, b.num_rows, 1000):
                part = b.slice(lo, 1000)
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(kept))), pa.array(shared.value.scores(part.column(at).to_pylist()))], [*kept, name])

    return docs.select(*[F.col(f"`{c}`") for c in kept], *([] if "text" in kept else ["text"])).mapInArrow(run, f"{fields}, `{name}` double")


def toxicity_report(docs: DataFrame, labels: DataFrame, folds: int = 5, held: int = 0, sample: int = 800) -> DataFrame:
    """Learn outside the held-out fold, score every row."""
    model = fit_toxicity(docs, labels.where(fold(F.col("doc_id"), folds) != held), sample)
    scored = score_toxicity(docs, model)
    return scored.select("doc_id", F.coalesce(fold(F.col("doc_id"), folds) == held, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
