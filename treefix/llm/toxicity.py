"""Toxicity by a bidirectional gated recurrent network with attention pooling.

Every word enters as a learned word vector and an attention pool over learned vectors of its character n-grams and
prefixes, so unseen spellings of a known stem count, and the n-gram that tells most counts most. Windows of
``WINDOW`` words, overlapping by half, cover the whole text; a document's score is the calibrated score of its
most toxic window.

The network is written and trained in numpy on a bounded sample of labelled rows: ``SAMPLE_ROWS`` for
each label, the smallest by hash of the id, as long as their texts together stay within ``SAMPLE_BYTES``.
Its vocabulary are the words and n-grams that tell most in the sample (``WORD_ROWS``, ``GRAM_ROWS``). First vectors
come from their label odds; then, in turns, the top window of each document under the current weights is taken
and the weights are fitted to those windows. Platt scaling on a part of the sample set aside gives
probabilities, weighted to the label shares of the whole labelled table. Weights are about a MB, whatever the corpus.

Null and empty texts have one empty window. Without labelled rows of both kinds, the
score is the share of label 1 (0 if there is no label). Of rows that repeat a labelled id one text is learned from.
Extra columns pass through; a column named as a result is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treefix.llm.shared import as_bytes, mixed, rows_of, tidied, word_hashes

WINDOW, STRIDE, HIDDEN, WORD_DIM, CHAR_DIM, ATTENTION = 64, 32, 8, 6, 6, 8
WORD_ROWS, GRAM_ROWS = 1 << 13, 1 << 14
SAMPLE_ROWS, SAMPLE_BYTES, LEAST_STEPS, THRESHOLD, CACHE, LEAST_SEEN, RATE, PART = 1500, 24 << 20, 120, 0.7, 60_000, 4, 0.3, 20_000
AT_ONCE = 500_000  # bytes of text that a worker splits into words together, besides one document
INNER, PREFIXES, LONGEST = (3, 4, 5), (6, 7, 8, 9, 10), 1024
_TABLE = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def words_of(text: bytes | None) -> list[bytes]:
    """Lower-cased words; one of over ``LONGEST`` bytes enters as several."""
    words = as_bytes(text).translate(_TABLE).split()
    if any(len(w) > LONGEST for w in words):
        words = [w[at : at + LONGEST] for w in words for at in range(0, len(w), LONGEST)]
    return words


def gram_hashes(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the character n-grams (``INNER``) and prefixes (``PREFIXES``) of whole words with their
    ends marked, word by word in one array, and where each word's begin (and the last ends)."""
    if len(words) > PART:  # in parts: the arrays on the way are many times the result
        parts = [gram_hashes(words[at : at + PART]) for at in range(0, len(words), PART)]
        bases = np.cumsum([0, *(ends[-1] for _, ends in parts)])
        return np.concatenate([g for g, _ in parts]), np.concatenate([[0], *(ends[1:] + b for (_, ends), b in zip(parts, bases))])
    marked = [b"^" + w + b"$" for w in words]
    sizes = np.fromiter(map(len, marked), dtype=np.int64, count=len(marked))
    held = np.frombuffer(b"".join(marked), dtype=np.uint8).astype(np.uint64)
    starts = np.cumsum(sizes) - sizes
    owner, left = np.repeat(np.arange(len(words)), sizes), np.repeat(np.cumsum(sizes), sizes) - np.arange(len(held))
    found, owners = [], []
    for n in (*INNER, *PREFIXES):
        own = np.flatnonzero(left >= n) if n in INNER else starts[sizes > n]  # a prefix lacks the end mark
        h = np.full(len(own), n, dtype=np.uint64)
        with np.errstate(over="ignore"):
            for k in range(n):
                h = (h ^ held[own + k]) * np.uint64(0x100000001B3)
        found.append(mixed(h))
        owners.append(owner[own])
    owners = np.concatenate(owners)
    order = np.argsort(owners, kind="stable")
    return np.concatenate(found)[order], np.concatenate([[0], np.cumsum(np.bincount(owners, minlength=len(words)))])


def place_in(vocabulary: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """Rows of hashes in a sorted vocabulary, from 1; 0 for others."""
    if not len(vocabulary):
        return np.zeros(len(hashes), dtype=np.int32)
    at = np.minimum(np.searchsorted(vocabulary, hashes), len(vocabulary) - 1)
    return np.where(vocabulary[at] == hashes, at + 1, 0).astype(np.int32)


def window_starts(n: int) -> range:
    return range(0, max(n - STRIDE, 1), STRIDE)


@dataclass
class Network:
    """The weights. ``p`` holds arrays by name; both directions lie side by side. Row 0 of the vectors stands for words
    outside the vocabulary, and as an n-gram it is part of every word; the last column of n-grams is what attention goes by."""

    p: dict[str, np.ndarray] = field(default_factory=dict)
    words: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))
    grams: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))
    scale: float = 1.0
    shift: float = 0.0
    prior: float | None = None  # set if there was nothing to learn from

    @classmethod
    def fresh(cls, seed: int = 7, words: np.ndarray | None = None, grams: np.ndarray | None = None) -> Network:
        rng = np.random.default_rng(seed)
        words, grams = (np.zeros(0, np.uint64) if x is None else x for x in (words, grams))
        d, h = WORD_DIM + CHAR_DIM, HIDDEN
        draw = lambda *s: (rng.standard_normal(s) / np.sqrt(s[-2] if len(s) > 1 else s[0])).astype(np.float32)
        p = {"word": 0.05 * rng.standard_normal((len(words) + 1, WORD_DIM)), "gram": 0.05 * rng.standard_normal((len(grams) + 1, CHAR_DIM + 1))}
        p["word"][0] = p["gram"][0] = 0
        for k in ("f", "b"):
            p |= {f"x{k}": draw(d, 3 * h), f"c{k}": np.zeros(3 * h, np.float32), f"u{k}": draw(h, 3 * h)}
        p |= {"wa": draw(2 * h, ATTENTION), "ba": np.zeros(ATTENTION, np.float32), "va": draw(ATTENTION), "wo": draw(2 * h), "bo": np.zeros(1, np.float32)}
        return cls({k: v.astype(np.float32) for k, v in p.items()}, words, grams)

    def rows_of(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Rows of words, rows of their n-grams word by word (row 0 first), and where each word's begin."""
        parts = []
        for at in range(0, len(words), PART):
            part = words[at : at + PART]
            hashes, ends = gram_hashes(part)
            rows = place_in(self.grams, hashes)
            known = np.flatnonzero(rows)
            owner = np.repeat(np.arange(len(part)), np.diff(ends))[known]
            sizes = 1 + np.bincount(owner, minlength=len(part))
            begin = np.concatenate([[0], np.cumsum(sizes)])
            held = np.zeros(begin[-1], np.int32)
            held[np.arange(len(known)) + owner + 1] = rows[known]
            parts.append((place_in(self.words, word_hashes(part, 1)), held, sizes))
        if not parts:
            return np.zeros(0, np.int32), np.zeros(0, np.int32), np.zeros(1, np.int64)
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]), np.concatenate([[0], np.cumsum(np.concatenate([p[2] for p in parts]))])

    def vectors(self, words: list[bytes]) -> np.ndarray:
        """Input vectors of words: the word's own, then the pool over its n-grams."""
        if not words:
            return np.zeros((0, WORD_DIM + CHAR_DIM), np.float32)
        return self.looked_up(*self.rows_of(words))[0]

    def looked_up(self, rows: np.ndarray, grams: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Vectors, and the attention that each n-gram gets."""
        held, first, sizes = self.p["gram"][grams], ends[:-1], np.diff(ends)
        e = held[:, CHAR_DIM]
        w = np.exp(e - np.repeat(np.maximum.reduceat(e, first), sizes))
        w /= np.repeat(np.add.reduceat(w, first), sizes)
        pooled = np.add.reduceat(held[:, :CHAR_DIM] * w[:, None], first, axis=0)
        return np.concatenate([self.p["word"][rows], pooled], axis=1).astype(np.float32), w

    def projected(self, x: np.ndarray) -> np.ndarray:
        return np.concatenate([x @ self.p["xf"] + self.p["cf"], x @ self.p["xb"] + self.p["cb"]], axis=-1)

    @staticmethod
    def padding() -> np.ndarray:
        """What stands for no word: the update gate stays shut, the state as it was."""
        row = np.zeros((1, 6 * HIDDEN), np.float32)
        row[0, :HIDDEN] = row[0, 3 * HIDDEN : 4 * HIDDEN] = 60
        return row

    def logits(self, table: np.ndarray, index: np.ndarray) -> np.ndarray:
        """Logits of windows: ``index`` (windows, WINDOW) are rows of ``table`` (projected inputs, row 0 padding)."""
        return self._run(table[index.T], index.T > 0)[0]

    def _run(self, x: np.ndarray, real: np.ndarray, keep: bool = False):
        """x: (steps, windows, 6 * HIDDEN). Also what the backward pass needs, if asked for."""
        steps, n, h = len(x), x.shape[1], HIDDEN
        states = np.zeros((steps, n, 2 * h), np.float32)
        memo = {}
        for k, (name, order) in enumerate((("f", range(steps)), ("b", range(steps - 1, -1, -1)))):
            u, s = self.p[f"u{name}"], np.zeros((n, h), np.float32)
            for t in order:
                xt, hu = x[t, :, 3 * h * k : 3 * h * (k + 1)], s @ u
                gates = np.tanh(0.5 * (xt[:, : 2 * h] + hu[:, : 2 * h])) * 0.5 + 0.5
                z, r = gates[:, :h], gates[:, h:]
                c = np.tanh(xt[:, 2 * h :] + r * hu[:, 2 * h :])
                new = c + z * (s - c)
                if keep:
                    memo[name, t] = (s, z, r, c, hu[:, 2 * h :])
                s = new
                states[t, :, h * k : h * (k + 1)] = s
        a = np.tanh(states @ self.p["wa"] + self.p["ba"])
        e = np.where(real, a @ self.p["va"], np.float32(-1e9))
        w = np.exp(e - e.max(axis=0))
        w /= w.sum(axis=0)
        pooled = np.einsum("tn,tnd->nd", w, states)
        return pooled @ self.p["wo"] + self.p["bo"][0], (states, a, w, pooled, memo)

    def gradients(self, x: np.ndarray, real: np.ndarray, target: np.ndarray, weight: np.ndarray):
        """Gradients of weighted log loss by weight name, and with respect to ``x`` (steps, windows, inputs)."""
        p, h = self.p, HIDDEN
        projected = np.where(real[..., None], self.projected(x), self.padding()[0])
        logit, (states, a, w, pooled, memo) = self._run(projected, real, keep=True)
        d_logit = (weight * (1 / (1 + np.exp(-np.clip(logit, -30, 30))) - target)).astype(np.float32) / len(target)
        g = {"wo": pooled.T @ d_logit, "bo": np.array([d_logit.sum()], np.float32)}
        d_pooled = d_logit[:, None] * p["wo"]
        d_states = w[..., None] * d_pooled
        d_w = np.einsum("nd,tnd->tn", d_pooled, states)
        d_e = w * (d_w - (w * d_w).sum(axis=0))
        d_a = d_e[..., None] * p["va"] * (1 - a * a)
        g |= {"va": np.einsum("tn,tna->a", d_e, a), "wa": np.einsum("tnd,tna->da", states, d_a), "ba": d_a.sum(axis=(0, 1))}
        d_states = d_states + d_a @ p["wa"].T
        d_x = np.zeros_like(x)
        steps = len(x)
        for k, (name, order) in enumerate((("f", range(steps - 1, -1, -1)), ("b", range(steps)))):
            u, carry = p[f"u{name}"], np.zeros((x.shape[1], h), np.float32)
            g_u, g_in = np.zeros_like(u), np.zeros((steps, x.shape[1], 3 * h), np.float32)
            for t in order:
                s, z, r, c, hun = memo[name, t]
                d = d_states[t, :, h * k : h * (k + 1)] + carry
                d_c = d * (1 - z) * (1 - c * c)
                d_z = d * (s - c) * z * (1 - z)
                d_r = d_c * hun * r * (1 - r)
                inner = np.concatenate([d_z, d_r, d_c * r], axis=1)
                g_u += s.T @ inner
                carry = d * z + inner @ u.T
                g_in[t] = np.concatenate([d_z, d_r, d_c], axis=1) * real[t][:, None]
            g |= {f"u{name}": g_u, f"x{name}": np.einsum("tnd,tng->dg", x, g_in), f"c{name}": g_in.sum(axis=(0, 1))}
            d_x += g_in @ p[f"x{name}"].T
        return g, d_x

    def descend(self, rows: np.ndarray, grams: np.ndarray, ends: np.ndarray, share: np.ndarray, x: np.ndarray, d_x: np.ndarray) -> None:
        """A gradient step of the vectors behind input vectors ``x``; those outside the vocabulary stay zero."""
        sizes = np.diff(ends)
        d_pool = np.repeat(d_x[:, WORD_DIM:], sizes, axis=0)
        lead = ((self.p["gram"][grams, :CHAR_DIM] - np.repeat(x[:, WORD_DIM:], sizes, axis=0)) * d_pool).sum(axis=1) * share
        np.subtract.at(self.p["gram"], grams, RATE * np.concatenate([d_pool * share[:, None], lead[:, None]], axis=1))
        np.subtract.at(self.p["word"], rows, RATE * d_x[:, :WORD_DIM])
        self.p["word"][0] = self.p["gram"][0] = 0

    def probability(self, logit: np.ndarray) -> np.ndarray:
        if self.prior is not None:
            return np.full(len(logit), self.prior)
        return 1 / (1 + np.exp(-np.clip(self.scale * logit + self.shift, -40, 40)))


class Scorer:
    """Scores texts by network; words' projected inputs are kept in a table of bounded size."""

    def __init__(self, net: Network, chunk: int = 2048):
        self.net, self.chunk = net, chunk
        self._reset()

    def _reset(self) -> None:
        self.rows: dict[bytes, int] = {}
        self.table = self.net.padding()

    def _index(self, words: list[bytes]) -> np.ndarray:
        rows = self.rows
        fresh = [w for w in dict.fromkeys(words) if w not in rows]
        for at in range(0, len(fresh), PART):
            part = fresh[at : at + PART]
            base = len(rows) + 1
            rows.update(zip(part, range(base, base + len(part))))
            new = self.net.projected(self.net.vectors(part))
            while base + len(part) > len(self.table):
                self.table = np.concatenate([self.table, np.zeros((max(4096, len(self.table)), self.table.shape[1]), np.float32)])
            self.table[base : base + len(part)] = new
        return np.fromiter(map(rows.__getitem__, words), dtype=np.int32, count=len(words))

    def windows(self, texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
        """Window rows of table indices, and where each text's windows begin. All words are looked up together."""
        split = [words_of(t) for t in texts]
        flat = self._index([w for words in split for w in words])
        sizes = np.array([len(w) for w in split])
        ends = np.cumsum(sizes)
        counts = np.maximum((np.maximum(sizes - STRIDE, 1) + STRIDE - 1) // STRIDE, 1)
        begin = np.concatenate([[0], np.cumsum(counts)])
        number = np.arange(begin[-1]) - np.repeat(begin[:-1], counts)
        first = np.repeat(ends - sizes, counts) + number * STRIDE
        at = first[:, None] + np.arange(WINDOW)[None, :]
        real = at < np.repeat(ends, counts)[:, None]
        index = np.where(real, flat[np.minimum(at, max(len(flat) - 1, 0))], 0) if len(flat) else np.zeros(at.shape, np.int32)
        return index, begin

    def all_windows(self, texts: list[bytes | None], at_once: int = 100) -> tuple[np.ndarray, np.ndarray]:
        """As ``windows``, some texts at a time, so that few words are Python objects at once."""
        found, ends = [], [np.zeros(1, dtype=np.int64)]
        for at in range(0, len(texts), at_once):
            index, begin = self.windows(texts[at : at + at_once])
            found.append(index.astype(np.int32))
            ends.append(begin[1:] + ends[-1][-1])
        return np.concatenate(found), np.concatenate(ends)

    def window_logits(self, index: np.ndarray) -> np.ndarray:
        parts = [self.net.logits(self.table, index[at : at + self.chunk]) for at in range(0, len(index), self.chunk)]
        return np.concatenate(parts)

    def score(self, texts: list[bytes | None]) -> np.ndarray:
        if len(self.rows) > CACHE:
            self._reset()
        index, begin = self.windows(texts)
        return self.net.probability(np.maximum.reduceat(self.window_logits(index), begin[:-1]).astype(np.float64))


def _telling(docs: list[np.ndarray], y: np.ndarray, most: int, buckets: int = 1 << 22) -> tuple[np.ndarray, np.ndarray]:
    """The sorted hashes that tell most about the label, at most ``most``, and their shrunk log odds of label 1.
    ``docs``: the distinct hashes of each document. Buckets are counted first, so only telling ones are counted one by one."""
    ones, zeros = max(float(y.sum()), 1.0), max(float((1 - y).sum()), 1.0)

    def strength(seen: np.ndarray, toxic: np.ndarray) -> np.ndarray:
        share = seen / (ones + zeros)
        gap = toxic / ones - (seen - toxic) / zeros
        return np.where(seen >= LEAST_SEEN, np.abs(gap) / np.sqrt(np.maximum(share * (1 - share), 1e-9) * (1 / ones + 1 / zeros)), 0.0)

    seen, toxic = np.zeros(buckets, np.float32), np.zeros(buckets, np.float32)
    for own, label in zip(docs, y):
        at = np.unique(own % np.uint64(buckets)).astype(np.int64)
        seen[at] += 1
        if label:
            toxic[at] += 1
    good = strength(seen, toxic) >= 2
    del seen, toxic
    left = [own[good[(own % np.uint64(buckets)).astype(np.int64)]] for own in docs]
    names, inverse = np.unique(np.concatenate([*left, np.zeros(0, np.uint64)]), return_inverse=True)
    label = np.repeat(y, [len(x) for x in left])
    seen, toxic = np.bincount(inverse, minlength=len(names)).astype(float), np.bincount(inverse, label, minlength=len(names))
    value = strength(seen, toxic)
    kept = np.flatnonzero(value >= 2)
    kept = np.sort(kept[np.lexsort((names[kept], -value[kept]))[:most]])
    seen, toxic = seen[kept], toxic[kept]
    odds = np.log((toxic + 0.5) / (ones + 1)) - np.log((seen - toxic + 0.5) / (zeros + 1))
    return names[kept], (odds * seen / (seen + 4)).astype(np.float32)


def fit(texts: list[bytes | None], labels: list[int], shares: tuple[int, int] | None = None, rounds: int = 3, epochs: int = 4, seed: int = 7) -> Network:
    """A network fitted to labelled texts. ``shares``: rows of label 0 and 1 in the whole table."""
    y = np.array(labels, dtype=np.float32)
    if len(y) == 0 or y.min() == y.max():
        return Network(Network.fresh(seed).p, prior=float(y.mean()) if len(y) else 0.0)
    rng = np.random.default_rng(seed)
    aside = rng.random(len(y)) < 0.2
    for label in (0, 1):  # both parts need both labels
        own = np.flatnonzero(y == label)
        aside[own[0]], aside[own[-1]] = False, True
    train = np.flatnonzero(~aside)

    def hashed(kind) -> list[np.ndarray]:
        return [np.unique(kind(sorted(set(words_of(texts[i]))))) for i in train]

    word_names, word_odds = _telling(hashed(lambda words: word_hashes(words, 1)), y[train], WORD_ROWS)
    gram_names, gram_odds = _telling(hashed(lambda words: gram_hashes(words)[0] if words else np.zeros(0, np.uint64)), y[train], GRAM_ROWS)
    net = Network.fresh(seed, word_names, gram_names)
    net.p["word"][1:, 0], net.p["gram"][1:, 0], net.p["gram"][1:, CHAR_DIM] = 0.5 * word_odds, 0.5 * gram_odds, 1.5 * np.abs(gram_odds)
    unique: dict[bytes, int] = {}
    for text in texts:
        for w in words_of(text):
            unique.setdefault(w, len(unique))
    names = list(unique)
    rows, grams, ends = net.rows_of(names)

    def own_grams(numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        sizes = ends[numbers + 1] - ends[numbers]
        cuts = np.concatenate([[0], np.cumsum(sizes)])
        return grams[np.arange(cuts[-1]) + np.repeat(ends[numbers] - cuts[:-1], sizes)], cuts

    state = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in net.p.items() if k not in ("word", "gram")}
    step = 0

    def adam(name: str, grad: np.ndarray, rate: float) -> None:
        m, v = state[name]
        m += 0.1 * (grad - m)
        v += 0.001 * (grad * grad - v)
        net.p[name] -= (rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)).astype(np.float32)

    balance = np.where(y == 1, 0.5 / max(y[train].mean(), 1e-3), 0.5 / max(1 - y[train].mean(), 1e-3)).astype(np.float32)
    for turn in range(rounds):
        scorer = Scorer(net)
        index, begin = scorer.all_windows(texts)
        if turn == 0:  # the window whose words speak most for label 1 together
            strength = np.concatenate([[0.0], *(np.maximum(net.vectors(names[at : at + PART])[:, [0, WORD_DIM]].max(axis=1), 0) for at in range(0, len(names), PART))])
            value = strength[_renamed(scorer, unique)[index]].sum(axis=1)
        else:
            value = scorer.window_logits(index)
        top = np.array([begin[i] + int(np.argmax(value[begin[i] : begin[i + 1]])) for i in range(len(y))])
        other = np.array([rng.integers(begin[i], begin[i + 1]) for i in train if y[i] == 0])
        chosen = np.concatenate([top[train], other])
        target = np.concatenate([y[train], np.zeros(len(other), np.float32)])
        weight = np.concatenate([balance[train], 0.3 * np.ones(len(other), np.float32)])
        own = _renamed(scorer, unique)[index[chosen]]  # 0 for padding, else the word's number plus 1
        nothing = 1 + len(train) // 20  # empty windows, which are clean
        own = np.concatenate([own, np.zeros((nothing, WINDOW), own.dtype)])
        target, weight = np.concatenate([target, np.zeros(nothing, np.float32)]), np.concatenate([weight, np.ones(nothing, np.float32)])
        for _ in range(max(epochs, -(-LEAST_STEPS * 128 // len(own)))):
            order = rng.permutation(len(own))
            for at in range(0, len(order), 128):
                part = order[at : at + 128]
                ids = own[part].T
                real = ids > 0
                used, place = np.unique(ids, return_inverse=True)
                numbers = used[used > 0] - 1
                x = np.zeros((len(used), WORD_DIM + CHAR_DIM), np.float32)
                if len(numbers):
                    held, cuts = own_grams(numbers)
                    x[used > 0], share = net.looked_up(rows[numbers], held, cuts)
                g, d_x = net.gradients(x[place.reshape(ids.shape)], real, target[part], weight[part])
                step += 1
                for name, grad in g.items():
                    adam(name, grad, 0.01 if turn < rounds - 1 else 0.003)
                if not len(numbers):
                    continue
                per_word = np.zeros_like(x)
                np.add.at(per_word, place.ravel(), d_x.reshape(-1, d_x.shape[2]))
                net.descend(rows[numbers], held, cuts, share, x[used > 0], per_word[used > 0])
    scorer = Scorer(net)
    held_out = np.flatnonzero(aside)
    index, begin = scorer.all_windows([texts[i] for i in held_out])
    logit = np.maximum.reduceat(scorer.window_logits(index), begin[:-1])
    ones, zeros = y[held_out].sum(), (1 - y[held_out]).sum()
    zero_share, one_share = shares or (int((1 - y).sum()), int(y.sum()))
    w = np.where(y[held_out] == 1, one_share / ones, zero_share / zeros)
    net.scale, net.shift = platt(logit, y[held_out], w / w.sum())
    return net


def _renamed(scorer: Scorer, unique: dict[bytes, int]) -> np.ndarray:
    """From the scorer's table rows to numbers in ``unique`` plus 1; 0 stays padding."""
    out = np.zeros(len(scorer.rows) + 1, dtype=np.int64)
    for w, row in scorer.rows.items():
        out[row] = unique[w] + 1
    return out


def platt(logit: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[float, float]:
    """Scale and shift of a weighted logistic fit, by damped Newton steps; a small penalty keeps separable data finite."""
    a, b = 1.0, 0.0
    for _ in range(60):
        q = 1 / (1 + np.exp(-np.clip(a * logit + b, -30, 30)))
        r, s = weight * (q - y), weight * np.maximum(q * (1 - q), 1e-6)
        g = np.array([(r * logit).sum() + 1e-3 * (a - 1), r.sum()])
        m = np.array([[(s * logit * logit).sum() + 1e-3, (s * logit).sum()], [(s * logit).sum(), s.sum() + 1e-9]])
        move = np.linalg.solve(m, g)
        move *= min(1.0, 2.0 / max(np.abs(move).max(), 1e-9))
        a, b = a - move[0], b - move[1]
        if np.abs(move).max() < 1e-7:
            break
    return float(max(a, 1e-3)), float(b)


def is_held_out(id_col: str = "doc_id"):
    return F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(3)) == 1


def train(docs: DataFrame, labels: DataFrame, per_label: int = SAMPLE_ROWS, most_bytes: int = SAMPLE_BYTES) -> Network:
    """Fits to at most ``per_label`` documents of each label, of ``most_bytes`` together, none of them held out."""
    known = labels.where(F.col("toxic").isin(0, 1)).where(~is_held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    counts = {r["toxic"]: r["count"] for r in known.groupBy("toxic").count().collect()}
    order = F.xxhash64(F.col("doc_id")), F.col("doc_id")
    picked = None
    for label in (0, 1):
        part = known.where(F.col("toxic") == label).orderBy(*order).limit(per_label)
        picked = part if picked is None else picked.unionByName(part)
    texts = docs.select("doc_id", F.col("text").cast("binary").alias("text")).join(F.broadcast(picked), "doc_id")  # at most 2 * per_label ids
    texts = texts.groupBy("doc_id", "toxic").agg(F.min(F.struct(F.coalesce(F.octet_length("text"), F.lit(0)).alias("size"), "text")).alias("t"))
    # at most 2 * per_label rows; of both labels alternately, while there is room
    turn = F.row_number().over(Window.partitionBy("toxic").orderBy(*order))
    sizes = texts.select("doc_id", "toxic", F.col("t.size").alias("size")).withColumn("turn", turn)
    room = F.sum("size").over(Window.orderBy("turn", "toxic").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    fits = sizes.withColumn("room", room).where(F.col("room") <= most_bytes).select("doc_id")
    rows = sorted((r["doc_id"], r["toxic"], bytes(r["text"] or b"")) for r in texts.select("doc_id", "toxic", "t.text").join(F.broadcast(fits), "doc_id").collect())
    return fit([r[2] for r in rows], [r[1] for r in rows], (counts.get(0, 0), counts.get(1, 0)) if len(counts) == 2 else None)


def score_toxicity(docs: DataFrame, net: Network, text_col: str = "text", score_col: str = "score", drop_text: bool = False) -> DataFrame:
    """The rows of ``docs`` with a score between 0 and 1; without their text if that is not needed."""
    shared = docs.sparkSession.sparkContext.broadcast(net)
    given = docs.drop(score_col)
    place = given.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value)
        for batch in batches:
            at = 0
            while at < batch.num_rows:
                texts, size, start = [], 0, at
                for (text,) in rows_of(iter([batch.slice(at).select([batch.schema.names[place]])]), batch.schema.names[place]):
                    raw = text.encode() if isinstance(text, str) else text
                    texts.append(raw)
                    size += len(raw or b"")
                    at += 1
                    if size > AT_ONCE:
                        break
                part = batch.slice(start, at - start)
                if drop_text:
                    part = part.select([n for n in part.schema.names if n != text_col])
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(scorer.score(texts))], names=[*part.schema.names, score_col])

    kept = [f for f in given.schema.fields if not (drop_text and f.name == text_col)]
    return given.mapInArrow(tidied(run), T.StructType([*kept, T.StructField(score_col, T.DoubleType())]))
