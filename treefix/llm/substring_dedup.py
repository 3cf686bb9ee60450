"""Removal of word sequences that occur more than once, by difference-cover anchors.

A window is ``window`` consecutive words of one document. A word goes if it
lies in a window whose words also start anywhere else in the corpus.

Only word positions whose residue modulo ``period`` lies in a difference cover
are hashed (6 of 31, 5 of 21 ...). For any two positions some shift below
``period`` brings both onto the cover, so two equal windows always share an
anchor of ``window - period + 1`` words at one offset. Anchors that occur twice
are extended: the full windows around them are hashed (96 bits) and compared.

Hot sequences: every task keeps one representative of a hash for the shuffle and
passes the other rows on, spread by row, so no key gathers more than
one row for each chunk of ``WORD_BUDGET`` words. Texts are joined by document.

Null texts have no words. Equal rows count as two places. Rows with a null id
are handled like others. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.llm.shared import WORD_BUDGET, RollingHash, as_bytes, mixed, release, rows_of, signed, stage, tidied, word_hashes

WINDOW, PERIOD = 35, 21
ROW_KEY = "doc_id bigint, th bigint"


def difference_cover(period: int) -> list[int]:
    """The smallest set of residues whose pairwise differences give all residues,
    found by depth-first search (perfect for 7, 13, 21, 31)."""

    def search(chosen: list[int], left: int) -> list[int] | None:
        if left == 0:
            return chosen if len({(a - b) % period for a in chosen for b in chosen}) == period else None
        for nxt in range(chosen[-1] + 1, period):
            if found := search([*chosen, nxt], left - 1):
                return found
        return None

    for size in range(1, period + 1):
        if size * (size - 1) + 1 >= period and (found := search([0], size - 1)):
            return found
    return list(range(period))


class _Chunk:
    """Hashed places of some documents; equal hashes within are told apart at once."""

    def __init__(self):
        self.hashes, self.second, self.places, self.rows, self.size = [], [], [], [], 0

    def add(self, doc_id, th, places: np.ndarray, first: np.ndarray, second: np.ndarray) -> None:
        self.hashes.append(first)
        self.second.append(second)
        self.places.append(places)
        self.rows.append((doc_id, th, len(places)))
        self.size += len(places)

    def batch(self) -> pa.RecordBatch:
        first, second, place = (np.concatenate(x) for x in (self.hashes, self.second, self.places))
        index = np.repeat(np.arange(len(self.rows)), [n for *_, n in self.rows])
        order = np.lexsort((second, first))
        a, b = first[order], second[order]
        same = (a[1:] == a[:-1]) & (b[1:] == b[:-1])
        repeated = np.zeros(len(a), dtype=bool)
        repeated[1:] |= same
        repeated[:-1] |= same
        head = np.ones(len(a), dtype=bool)  # the row that stands for its hash
        head[1:] = ~same
        state = np.where(head, np.where(repeated, KNOWN_HEAD, OPEN), KNOWN)
        own = index[order]
        key, extra = a.copy(), (b >> np.uint64(32)).astype(np.uint32)
        # known rows are dealt by document: nothing is compared, and equal values shuffle small
        spread = mixed(np.array([(r[1] or 0) & ((1 << 64) - 1) for r in self.rows], dtype=np.uint64) + np.arange(len(self.rows), dtype=np.uint64))
        key[~head], extra[~head] = spread[own[~head]], 0
        back = np.argsort(order)  # documents in order: their rows compress together
        spot = (place[order].astype(np.int64) << 2 | state)[back]
        ids = pa.array([r[0] for r in self.rows], pa.int64()).take(pa.array(index))
        ths = pa.array([r[1] for r in self.rows], pa.int64()).take(pa.array(index))
        return pa.RecordBatch.from_arrays([ids, ths, pa.array(spot.astype(np.int32)), pa.array(signed(key[back])), pa.array(extra[back].view(np.int32))], names=["doc_id", "th", "spot", "key", "extra"])


#: Of a row: compared with others; known to be repeated; both, as the first of its chunk
OPEN, KNOWN, KNOWN_HEAD = 0, 1, 2
PLACES = f"{ROW_KEY}, spot int, key bigint, extra int"


def _anchors(window: int, period: int):
    width, cover = window - period + 1, difference_cover(period)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        roll, chunk, words_held = RollingHash(0x9E3779B97F4A7C15), _Chunk(), 0
        for doc_id, th, text in rows_of(batches, "doc_id", "th", "text"):
            words = as_bytes(text).split()
            if len(words) < window:
                continue
            last = len(words) - width
            places = np.sort(np.concatenate([np.arange(r, last + 1, period) for r in cover]))
            first = roll.windows(word_hashes(words), places, width)
            chunk.add(doc_id, th, places, first, np.zeros(len(places), dtype=np.uint64))
            words_held += len(words)
            if words_held >= WORD_BUDGET:
                yield chunk.batch()
                chunk, words_held = _Chunk(), 0
        if chunk.size:
            yield chunk.batch()

    return run


def _windows(window: int, period: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        roll, other = RollingHash(0x9E3779B97F4A7C15), RollingHash(0xD1B54A32D192ED03)
        chunk = _Chunk()
        for doc_id, th, text, anchors in rows_of(batches, "doc_id", "th", "text", "anchors"):
            words = as_bytes(text).split()
            last = len(words) - window
            edge = np.zeros(len(words) + 2, dtype=np.int32)  # starts from which an anchor is reached
            at = np.asarray(anchors, dtype=np.int64)
            np.add.at(edge, np.maximum(at - period + 1, 0), 1)
            np.add.at(edge, at + 1, -1)
            starts = np.flatnonzero(np.cumsum(edge)[: last + 1] > 0)
            chunk.add(doc_id, th, starts, roll.windows(word_hashes(words), starts, window), other.windows(word_hashes(words, 7), starts, window))
            if chunk.size >= WORD_BUDGET:
                yield chunk.batch()
                chunk = _Chunk()
        if chunk.size:
            yield chunk.batch()

    return run


def _repeated(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From rows sorted by key and extra: those that equal a neighbour, and the
    known ones. Holds one row between batches, however large a group is."""
    held, held_sent = None, False
    for batch in batches:
        table = pa.Table.from_batches([batch] if held is None else [held, batch]).combine_chunks()
        key, extra, spot = (table.column(c).to_numpy() for c in ("key", "extra", "spot"))
        known, compared = (spot & 3) != OPEN, (spot & 3) != KNOWN
        same = (key[1:] == key[:-1]) & (extra[1:] == extra[:-1]) & compared[1:] & compared[:-1]
        keep = known.copy()
        keep[1:] |= same
        keep[:-1] |= same
        if held is not None and held_sent:
            keep[0] = False
        if len(key):
            last_sent = bool(keep[-1]) or (len(key) == 1 and held_sent)
            out = table.filter(pa.array(keep))
            out = pa.table([out.column("doc_id"), out.column("th"), pa.array(spot[keep] >> 2)], names=["doc_id", "th", "place"])
            held, held_sent = table.slice(len(key) - 1).combine_chunks().to_batches()[0], last_sent
            yield from out.to_batches()


def _places_seen_twice(found: DataFrame) -> DataFrame:
    dealt = found.repartition("key").sortWithinPartitions("key", "extra", F.col("spot").bitwiseAND(3) == KNOWN)
    rows = dealt.mapInArrow(tidied(_repeated), f"{ROW_KEY}, place int")
    return rows.groupBy("doc_id", "th").agg(F.collect_set("place").alias("places"))


def _joined(docs: DataFrame, places: DataFrame, name: str) -> DataFrame:
    p = places.select(F.col("doc_id").alias("p_id"), F.col("th").alias("p_th"), F.col("places").alias(name))
    return docs.join(p, docs["doc_id"].eqNullSafe(p["p_id"]) & (docs["th"] == p["p_th"]), "left").drop("p_id", "p_th")


def _digest(words: list[bytes]) -> str:
    return hashlib.sha256(b" ".join(words)).hexdigest()


_GAP = re.compile(rb"[^\x20\x09-\x0D]+")


def _cut(text: bytes, gone: np.ndarray) -> bytes:
    """The text without the marked words; what stood between kept words stays."""
    out, start = [], 0
    for n, m in enumerate(_GAP.finditer(text)):
        if gone[n]:
            out.append(text[start : m.start()])
            start = m.end()
    return b"".join([*out, text[start:]])


def _settled(window: int, with_text: bool):
    """Documents without a repeated anchor are finished here; the others keep their text."""

    def run(batches):
        rows = []
        for doc_id, th, text, anchors in rows_of(batches, "doc_id", "th", "text", "anchors"):
            open_ = anchors is not None
            words = [] if open_ else as_bytes(text).split()
            rows.append((doc_id, th, text if open_ or with_text else None, anchors, None if open_ else len(words), None if open_ else _digest(words)))
            if len(rows) >= 512:
                yield _table(rows)
                rows = []
        if rows:
            yield _table(rows)

    def _table(rows):
        kinds = (pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.int32()), pa.int64(), pa.string())
        names = ["doc_id", "th", "text", "anchors", "n_words", "sha"]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=names)

    return run


def _finished(window: int, with_text: bool):
    def run(batches):
        rows = []
        for doc_id, th, text, starts in rows_of(batches, "doc_id", "th", "text", "starts"):
            words = as_bytes(text).split()
            edge = np.zeros(len(words) + window + 1, dtype=np.int32)
            at = np.asarray(starts or [], dtype=np.int64)
            np.add.at(edge, at, 1)
            np.add.at(edge, at + window, -1)
            gone = np.cumsum(edge)[: len(words)] > 0
            kept = [w for w, g in zip(words, gone) if not g]
            new = (text if not gone.any() else _cut(as_bytes(text), gone)) if with_text else None
            rows.append((doc_id, th, len(words), int(gone.sum()), _digest(kept), new))
            if len(rows) >= 512:
                yield _table(rows)
                rows = []
        if rows:
            yield _table(rows)

    def _table(rows):
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
        names = ["doc_id", "th", "n_words", "n_removed", "kept_sha256", "kept_text"]
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=names)

    return run


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, period: int = PERIOD, with_text: bool = True) -> DataFrame:
    """One row for each input row: ``doc_id, n_words, n_removed, kept_sha256`` and,
    if ``with_text``, ``kept_text`` (null for a null text)."""
    if not 1 <= period <= window:
        raise ValueError("the period must lie between 1 and the window")
    d = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.xxhash64(F.col(text_col)).alias("th"), F.col(text_col).cast("binary").alias("text"))
    anchors = _places_seen_twice(d.mapInArrow(tidied(_anchors(window, period)), PLACES))
    states = f"{ROW_KEY}, text binary, anchors array<int>, n_words bigint, sha string"
    state = stage(_joined(d, anchors, "anchors").mapInArrow(tidied(_settled(window, with_text)), states), "repeats")
    release(docs.sparkSession)
    open_ = state.where(F.col("anchors").isNotNull()).select("doc_id", "th", "text", "anchors")
    starts = _places_seen_twice(open_.mapInArrow(tidied(_windows(window, period)), PLACES))
    result = f"{ROW_KEY}, n_words bigint, n_removed bigint, kept_sha256 string, kept_text binary"
    cut = _joined(open_.drop("anchors"), starts, "starts").mapInArrow(tidied(_finished(window, with_text)), result)
    still = state.where(F.col("anchors").isNull()).select("doc_id", "th", "n_words", F.lit(0).cast("bigint").alias("n_removed"), F.col("sha").alias("kept_sha256"), F.col("text").alias("kept_text"))
    both = still.unionByName(cut).withColumn("kept_text", F.col("kept_text").cast("string"))
    return both if with_text else both.drop("kept_text")
