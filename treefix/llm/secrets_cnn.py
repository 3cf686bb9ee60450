"""Secret scan: base patterns, and a character convolutional network over every candidate.

Base findings (``assign``, ``access``, ``hex``) are matches of fixed patterns and always reported. Further
candidates are all long tokens and all values given to names that sound secret. Each candidate,
base findings too, is scored whole with its context by a small network in numpy:
character vectors with a mark for the candidate, one convolution, the largest response inside
and anywhere, a logistic output. Where candidates that reach the threshold overlap, the one of highest score is reported. It is trained on labelled findings that a seeded
generator writes (keys of known forms against hashes of files, paths, names, dates and versions), so
a result depends on nothing but the text. Scores are calibrated by Platt scaling on findings set
aside; the threshold is the highest that keeps ``RECALL`` of the true ones among others set aside.
Candidates at or above it are reported as ``learned``.

Null and empty texts have no finding. Each input row gives one row, also when rows repeat.
Spans are in code points, the end exclusive.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import re
from bisect import bisect_right
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.llm.shared import rows_of, tidied
from treefix.llm.toxicity import platt

# Base patterns and the least sizes of what they must match
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")  # runs are maximal, so shorter ones are those that fail
ASSIGN_LEAST, ACCESS_LEAST = 6, 20
KINDS = ("assign", "access", "hex", "learned")
NAMED = re.compile(r"""(?:pwd|passphrase|credential|auth|private_?key|access_?key|client_?key|bearer)["']?\x20*[:=]?\x20*["']?([A-Za-z0-9+/_.=-]{8,})""", re.IGNORECASE | re.ASCII)
LONG = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{20,}")
_HINTS, _NAMES = ("passw", "secret", "token", "api"), ("pwd", "passphrase", "credential", "auth", "key", "bearer")

# A candidate has at least INSIDE places
LEFT, INSIDE, RIGHT, DIM, FILTERS, REACH, RECALL = 24, 40, 8, 8, 24, 5, 0.98
PLACES = LEFT + INSIDE + RIGHT
PIECE = 4096  # so many places go through the convolution at once


def base_spans(text: str) -> list[tuple[int, int, int, int, int]]:
    """(start, kind, end, value start, value end) of the base findings, in order of start and kind."""
    found = []
    low = text.lower()
    if any(h in low for h in _HINTS):
        found += [(m.start(), 0, m.end(), m.start(2), m.end(2)) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LEAST]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end(), m.start(), m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LEAST]
    found += [(m.start(), 2, m.end(), m.start(), m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def candidates(text: str, base: list[tuple]) -> list[tuple[int, int]]:
    """Spans that may be secrets and don't lie within a base finding; they may overlap."""
    found = {m.span() for m in LONG.finditer(text)}
    low = text.lower()
    if any(h in low for h in _NAMES):
        found |= {m.span(1) for m in NAMED.finditer(text)}
    taken = sorted((s, e) for s, _, e, *_ in base)
    starts, reach = [s for s, _ in taken], list(accumulate((e for _, e in taken), max))
    return [(s, e) for s, e in sorted(found) if not (at := bisect_right(starts, s)) or reach[at - 1] < e]


def resolved(scored: list[tuple[int, int, float]]) -> list[tuple[int, int]]:
    """Of overlapping spans the one of highest score, the first and longest of equals."""
    kept: list[tuple[int, int]] = []
    for start, end, _ in sorted(scored, key=lambda x: (-x[2], x[0], -x[1])):
        at = bisect_right(kept, (start, end))
        if (at == 0 or kept[at - 1][1] <= start) and (at == len(kept) or end <= kept[at][0]):
            kept.insert(at, (start, end))
    return kept


def encoded(text: str, start: int, end: int) -> np.ndarray:
    """Character numbers of a candidate in its context; those of the candidate are above 128."""
    left, own, right = text[max(0, start - LEFT) : start], text[start:end], text[end : end + RIGHT]
    row = np.zeros(LEFT + max(INSIDE, len(own)) + RIGHT, dtype=np.int64)
    for at, part, mark in ((LEFT - len(left), left, 0), (LEFT, own, 128), (len(row) - RIGHT, right, 0)):
        row[at : at + len(part)] = [min(ord(c), 127) + mark for c in part]
    return row


@dataclass
class CharNet:
    p: dict[str, np.ndarray]
    scale: float = 1.0
    shift: float = 0.0
    threshold: float = 0.5

    def forward(self, rows: list[np.ndarray]):
        sizes = np.array([len(r) for r in rows])
        table = np.zeros((len(rows), sizes.max()), dtype=np.int64)
        for i, r in enumerate(rows):
            table[i, : len(r)] = r
        n = table.shape[1] - REACH + 1
        x, place, width = self.p["chars"][table], np.arange(n)[None, :], (sizes - LEFT - RIGHT)[:, None]
        unrolled = np.concatenate([x[:, k : k + n] for k in range(REACH)], axis=2)
        act = np.maximum(unrolled @ self.p["conv"] + self.p["bias"], 0) * (place < sizes[:, None] - REACH + 1)[..., None]
        own = (place >= LEFT - 2) & (place < LEFT - 2 + width)
        inside = act * own[..., None]
        length = (table[:, LEFT : LEFT + INSIDE] > 0).mean(axis=1, keepdims=True)
        pooled = np.concatenate([inside.max(axis=1), act.max(axis=1), inside.sum(axis=1) / width, length], axis=1)
        return pooled @ self.p["out"] + self.p["out_bias"][0], (table, unrolled, act, own, width, inside.argmax(axis=1), act.argmax(axis=1), pooled)

    def long_logit(self, row: np.ndarray) -> float:
        """The logit of one row, a piece of the convolution at a time."""
        n, width = len(row) - REACH + 1, len(row) - LEFT - RIGHT
        best_in, best, total = np.zeros(FILTERS), np.zeros(FILTERS), np.zeros(FILTERS)
        for at in range(0, n, PIECE):
            size = min(PIECE, n - at)
            x = self.p["chars"][row[at : at + size + REACH - 1]]
            act = np.maximum(np.concatenate([x[k : k + size] for k in range(REACH)], axis=1) @ self.p["conv"] + self.p["bias"], 0)
            inside = act[max(0, LEFT - 2 - at) : max(0, LEFT - 2 + width - at)]
            best, total = np.maximum(best, act.max(axis=0)), total + inside.sum(axis=0)
            if len(inside):
                best_in = np.maximum(best_in, inside.max(axis=0))
        pooled = np.concatenate([best_in, best, total / width, [(row[LEFT : LEFT + INSIDE] > 0).mean()]])
        return float(pooled @ self.p["out"] + self.p["out_bias"][0])

    def logits(self, rows: list[np.ndarray]) -> np.ndarray:
        """By length, so that little is padded."""
        out = np.zeros(len(rows))
        order = sorted(range(len(rows)), key=lambda i: len(rows[i]))
        while order:
            size = len(rows[order[0]])
            if size > PIECE:
                first = order.pop(0)
                out[first] = self.long_logit(rows[first])
                continue
            part = [i for i in order[: max(1, 256 * PLACES // size)] if len(rows[i]) <= 2 * size]
            out[part] = self.forward([rows[i] for i in part])[0]
            order = order[len(part) :]
        return out

    def probability(self, rows: list[np.ndarray]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.scale * self.logits(rows) + self.shift, -40, 40)))

    def gradients(self, rows: list[np.ndarray], y: np.ndarray) -> dict[str, np.ndarray]:
        logit, (table, unrolled, act, own, width, best_in, best, pooled) = self.forward(rows)
        d = ((1 / (1 + np.exp(-np.clip(logit, -30, 30)))) - y) / len(y)
        d_pool = d[:, None] * self.p["out"]
        d_act = np.zeros_like(act)
        i, f = np.arange(len(y))[:, None], np.arange(FILTERS)[None, :]
        np.add.at(d_act, (i, best_in, f), d_pool[:, :FILTERS] * (pooled[:, :FILTERS] > 0))
        np.add.at(d_act, (i, best, f), d_pool[:, FILTERS : 2 * FILTERS])
        d_act += d_pool[:, None, 2 * FILTERS : 3 * FILTERS] * (own / width)[..., None]
        d_act *= act > 0
        flat = d_act.reshape(-1, FILTERS)
        n = act.shape[1]
        d_x = np.zeros((*table.shape, DIM))
        d_unrolled = d_act @ self.p["conv"].T
        for k in range(REACH):
            d_x[:, k : k + n] += d_unrolled[:, :, k * DIM : (k + 1) * DIM]
        d_chars = np.zeros_like(self.p["chars"])
        np.add.at(d_chars, table, d_x)
        return {"out": pooled.T @ d, "out_bias": np.array([d.sum()]), "conv": unrolled.reshape(-1, REACH * DIM).T @ flat, "bias": flat.sum(axis=0), "chars": d_chars}


def labelled_findings(n: int, seed: int = 11) -> tuple[list[np.ndarray], np.ndarray]:
    """Seeded findings and labels: true secrets and things that look like them."""
    rng = np.random.default_rng(seed)
    alnum = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    syllables = "the an re tion er or st nd ea en ment ung lich der que eau ar os con ing th ou".split()
    pick = lambda options: options[rng.integers(len(options))]
    chars = lambda pool, a, b: "".join(pool[i] for i in rng.integers(0, len(pool), rng.integers(a, b)))
    word = lambda: "".join(pick(syllables) for _ in range(rng.integers(1, 5)))
    onsets, nuclei, codas = "b c d f g h k l m n p r s t v w z ch sch pf st bl tr th".split() + [""], "a e i o u ei ai au eau ou ie io".split(), "n r t l m s ng ch cht nd x rt".split() + [""] * 4
    syllable = lambda: pick(onsets) + pick(nuclei) + pick(codas)
    made = lambda a, b: "".join(syllable() for _ in range(rng.integers(a, b)))
    prose = lambda k: " ".join(word() for _ in range(k))

    letters = alnum[:52]
    given = ["pwd=", 'pwd: "', "passphrase=", "passphrase: ", "credential=", 'auth="', "auth: ", "private_key=", "access_key = ", "client_key: ", "bearer="]

    def secret() -> tuple[str, str]:
        if rng.random() < 0.3:  # without digits, some of them made of words: their names tell
            return pick(given), pick([lambda: chars(letters, 12, 40), lambda: "".join(made(1, 3).title() for _ in range(rng.integers(3, 6))), lambda: pick("-_.").join(made(1, 3) for _ in range(rng.integers(3, 6))), lambda: "".join(word().title() for _ in range(4)), lambda: chars(letters + "_-", 10, 24)])()
        value = pick([
            lambda: pick(["ghp_", "gho_", "sk_live_", "sk-", "xoxb-", "glpat-", "AIza", "npm_", "hf_"]) + chars(alnum, 24, 40),
            lambda: chars(alnum, 20, 48), lambda: base64.b64encode(rng.bytes(int(rng.integers(18, 40)))).decode(),
            lambda: "eyJ" + chars(alnum, 18, 30) + "_" + chars(alnum, 10, 30), lambda: rng.bytes(int(rng.integers(12, 24))).hex(), lambda: chars(alnum + "_-", 10, 24),
        ])()
        before = pick(["password=", 'token = "', "secret: ", "api_key=", "Authorization: Bearer ", 'auth="', "pwd=", "private_key: ", "access_key = ", "credential ", "use ", "key "])
        return before, value

    def plain() -> tuple[str, str]:
        if rng.random() < 0.4:  # without digits
            if rng.random() < 0.4:  # words after a name that gives nothing
                return pick(["auth", "the auth", "credential ", "credential", "bearer ", "private key ", "access key ", "passphrase ", "pwd "]), made(1, 4) + word() + pick(["tion", "ity", "ized", "entication", "management", "ungen"])
            return pick(["", "see ", "path: ", "file ", "from ", "the "]), pick([
                lambda: "-".join(word() for _ in range(5)) + "-" + word(), lambda: "_".join(word() for _ in range(5)) + "_" + word(), lambda: "/".join(word() for _ in range(6)), lambda: "/".join(chars("abcdefghij", 1, 4) for _ in range(rng.integers(8, 30))), lambda: made(7, 12), lambda: made(7, 12), lambda: made(6, 10).capitalize(), lambda: "-".join(made(2, 4) for _ in range(4)), lambda: word() + word() + word() + word() + word() + word(),
                lambda: "".join(word().title() for _ in range(6)), lambda: pick("=-_/+") * int(rng.integers(20, 80)), lambda: (word() + pick("=-_/") * 3) * 4,
            ])()
        value = pick([
            lambda: "-".join(word() for _ in range(4)) + "-" + str(rng.integers(1, 99)), lambda: "_".join(word() for _ in range(4)) + str(rng.integers(0, 9)),
            lambda: "/".join([word(), word(), word(), f"v{rng.integers(1, 9)}", word()]), lambda: f"20{rng.integers(10, 30)}-{rng.integers(10, 13)}-{rng.integers(10, 29)}T{rng.integers(10, 24)}-{rng.integers(10, 60)}-00",
            lambda: "".join(word().title() for _ in range(4)) + str(rng.integers(0, 99)), lambda: word() + "=" * 12 + str(rng.integers(0, 99)) + "-" * 8, lambda: str(rng.integers(10**9, 10**10)) * 2,
            lambda: word() + word() + word() + word() + str(rng.integers(1900, 2030)),
        ])()
        before = pick(["", "see ", "path: ", "file ", "version ", "from ", "author: ", "the ", "order ", "id ", "key "])
        return before, value

    rows, y = [], rng.random(n) < 0.5
    for true in y:
        before, value = secret() if true else plain()
        lead = prose(3) + " " + before
        rows.append(encoded(lead + value + " " + prose(2), len(lead), len(lead) + len(value)))
    return rows, y.astype(np.float64)


@functools.lru_cache(maxsize=1)
def trained(n: int = 8000, epochs: int = 8, seed: int = 11) -> CharNet:
    """The network, its calibration and its threshold; the same in every process."""
    rows, y = labelled_findings(n, seed)
    rng = np.random.default_rng(seed)
    net = CharNet({"chars": 0.3 * rng.standard_normal((256, DIM)), "conv": rng.standard_normal((REACH * DIM, FILTERS)) / np.sqrt(REACH * DIM), "bias": np.zeros(FILTERS), "out": 0.1 * rng.standard_normal(3 * FILTERS + 1), "out_bias": np.zeros(1)})
    cut = n * 3 // 4
    moments, step = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in net.p.items()}, 0
    for _ in range(epochs):
        order = rng.permutation(cut)
        for at in range(0, cut, 64):
            part, step = order[at : at + 64], step + 1
            for k, g in net.gradients([rows[i] for i in part], y[part]).items():
                m, v = moments[k]
                m += 0.1 * (g - m)
                v += 0.001 * (g * g - v)
                net.p[k] -= 0.01 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    mid = (cut + n) // 2  # one part to calibrate on, another for the threshold
    net.scale, net.shift = platt(net.logits(rows[cut:mid]), y[cut:mid], np.full(mid - cut, 1 / (mid - cut)))
    net.threshold = float(min(0.9, np.quantile(net.probability(rows[mid:])[y[mid:] == 1], 1 - RECALL)))
    return net


def joined(spans: list[tuple]) -> str:
    return ",".join(f"{KINDS[kind]}:{start}:{end}" for start, kind, end, *_ in spans)


MASK = "[SECRET]"


def _scan(net: CharNet, mask: bool):
    names = ["n_assign", "n_access", "n_hex", "base_sha256", "spans", "scores", "masked"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(pa.float64()), pa.string()]

    def one(text: str | None) -> tuple:
        base = base_spans(text or "")
        more = candidates(text or "", base)
        every = [(s, e) for s, _, e, *_ in base] + more
        score = net.probability([encoded(text, s, e) for s, e in every]) if every else np.zeros(0)
        learned = resolved([(s, e, v) for (s, e), v in zip(more, score[len(base) :]) if v >= net.threshold])
        spans = base + [(s, 3, e, s, e) for s, e in learned]
        held = {(s, e): float(v) for (s, e), v in zip(every, score)}
        spans.sort()
        new = text
        if mask and spans:
            out, at = [], 0
            for _, _, _, a, b in sorted(spans, key=lambda x: x[3:]):
                if b > at:
                    out += [text[at : max(a, at)], MASK]
                    at = b
            new = "".join([*out, text[at:]])
        count = [sum(k == n for _, k, *_ in base) for n in range(3)]
        digest = hashlib.sha256(joined(base).encode()).hexdigest()
        return (*count, digest, joined(spans), [held[s, e] for s, _, e, *_ in spans], new if mask else None)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                found = [one(text) for (text,) in rows_of(iter([part]), "text")]
                yield pa.RecordBatch.from_arrays([part.column(0), *[pa.array(c, k) for c, k in zip(zip(*found), kinds)]], names=["doc_id", *names])

    return run


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", mask: bool = False) -> DataFrame:
    """``doc_id, n_assign, n_access, n_hex, base_sha256, spans, scores`` and, if ``mask``,
    ``masked``: the text with the values of all findings replaced (null stays null)."""
    d = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    result = "doc_id bigint, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string, scores array<double>, masked string"
    found = d.mapInArrow(tidied(_scan(trained(), mask)), result)
    return found if mask else found.drop("masked")


def mask_secrets(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` with all columns, findings in the text masked."""
    net, columns = trained(), docs.columns
    scan = _scan(net, True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = columns.index(text_col)
        for batch in batches:
            text = pa.RecordBatch.from_arrays([pa.array(range(batch.num_rows), pa.int64()), batch.column(place)], names=["doc_id", "text"])
            new = pa.concat_arrays([b.column(b.num_columns - 1) for b in scan(iter([text]))]) if batch.num_rows else batch.column(place)
            yield pa.RecordBatch.from_arrays([new if n == place else c for n, c in enumerate(batch.columns)], names=batch.schema.names)

    return docs.mapInArrow(tidied(run), docs.schema)
