"""Near duplicates by SimHash, found over pivot distance tables.

Fingerprint: a bit is 1 if it is set in over half of the XXH64 hashes of a text's
word shingles. Two fingerprints link at ``radius`` or fewer differing bits.

Search. The 64 bits are split into six blocks and every block gets reference
fingerprints. The table stores, for each fingerprint, its Hamming distance to
each reference within the block; the references are chosen as a resolving set, so
that equal distances to all of them mean equal blocks. A distance differs between
two fingerprints by no more than they differ, and four differing bits leave at
least two of six blocks alone: links therefore have equal coordinates in some
pair of blocks, and those coordinates are the join key. Within a key, pairs whose largest
difference to any of the whole-width references exceeds the radius
are discarded, and the survivors are verified bit by bit.

Copies of one fingerprint are one node. A key keeps only a spanning forest of its links, so
rows out never exceed rows in. Keys with more than ``KEY_LIMIT`` members are dealt to
several tasks, a pair of member groups each, which still compares all members.

Null or empty texts have no words: fingerprint zero, linked like any other. Rows with a null
id get a fingerprint; their component is the smallest id that is known in it (null if
there is none). Repeated rows are returned as often as they occur.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.llm.shared import as_bytes, hot_join, hot_keys, release, rows_of, stage, tidied

SHINGLE, RADIUS = 4, 4
BLOCKS = ((0, 11), (11, 11), (22, 11), (33, 11), (44, 10), (54, 10))
KEY_LIMIT = 4096
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def fingerprint(text: bytes | None, shingle: int = SHINGLE) -> int:
    """The fingerprint of one text as an unsigned number."""
    words = as_bytes(text).translate(_LOWER).split()
    if not words:
        return 0
    if len(words) < shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), 42)
    digest, n = xxhash.xxh64_intdigest, len(words) - shingle + 1
    shifted = zip(*(words[k:] for k in range(shingle)))
    hashes = np.fromiter((digest(b" ".join(s), 42) for s in shifted), dtype="<u8", count=n)
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, n, 65536):
        ones += np.unpackbits(hashes[at : at + 65536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def _fingerprints(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, found = [], []

        def out():
            return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.array(found, dtype=np.uint64).view(np.int64))], names=["doc_id", "fp"])

        for doc_id, text in rows_of(batches, "doc_id", "text"):
            ids.append(doc_id)
            found.append(fingerprint(text, shingle))
            if len(ids) == 4096:
                yield out()
                ids, found = [], []
        if ids:
            yield out()

    return run


def resolving_set(bits: int) -> list[int]:
    """References within a block whose distances tell all its values apart: zero
    and values that split the remaining classes best, picked greedily."""
    values = np.arange(1 << bits, dtype=np.uint64)
    chosen: list[int] = []
    classes = np.zeros(len(values), dtype=np.int64)
    rng = np.random.default_rng(bits)
    while len(np.unique(classes)) < len(values):
        pool = {0, *rng.integers(0, 1 << bits, 24).tolist()} - set(chosen)
        best = max(sorted(pool), key=lambda p: len(np.unique(classes * 64 + np.bitwise_count(values ^ np.uint64(p)))))
        chosen.append(best)
        _, classes = np.unique(classes * 64 + np.bitwise_count(values ^ np.uint64(best)), return_inverse=True)
    return chosen


def references() -> np.ndarray:
    """Whole-width references for the discard test: rows of a 64 x 64 Hadamard matrix,
    whose distances differ as evenly as possible between unlike fingerprints."""
    rows = np.array([[bin(a & b).count("1") & 1 for b in range(64)] for a in range(0, 64, 4)], dtype=np.uint8)
    return np.packbits(rows, axis=1, bitorder="little").view("<u8").ravel()


def _table():
    """For each fingerprint a row for each pair of blocks: the pair and its coordinates."""
    pivots = [np.array(resolving_set(n), dtype=np.uint64) for _, n in BLOCKS]
    pairs = list(combinations(range(len(BLOCKS)), 2))

    def run(batches):
        for batch in batches:
            fp = batch.column(0).to_numpy().view(np.uint64)
            coordinates = []
            for (start, n), refs in zip(BLOCKS, pivots):
                part = (fp >> np.uint64(start)) & np.uint64((1 << n) - 1)
                packed = np.zeros(len(fp), dtype=np.uint64)
                for p in refs:  # a distance within a block is below 16
                    packed = (packed << np.uint64(4)) | np.bitwise_count(part ^ p).astype(np.uint64)
                coordinates.append(packed.view(np.int64))
            for k, (a, b) in enumerate(pairs):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(fp), k, dtype=np.int32)), pa.array(coordinates[a]), pa.array(coordinates[b]), batch.column(0)], names=["pair", "left", "right", "fp"])

    return run


class _Forest:
    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = x = self.up[self.up[x]]
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.root(a), self.root(b)
        self.up[max(a, b)] = min(a, b)
        return a != b


def linked(members: np.ndarray, radius: int, refs: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of the links within ``members``."""
    table = np.bitwise_count(members[:, None] ^ refs[None, :]).astype(np.int8)
    forest, found = _Forest(len(members)), []
    for i in range(len(members) - 1):
        near = np.flatnonzero(np.abs(table[i + 1 :, 0] - table[i, 0]) <= radius) + i + 1
        if len(near):
            near = near[np.abs(table[near] - table[i]).max(axis=1) <= radius]
            near = near[np.bitwise_count(members[near] ^ members[i]) <= radius]
            found += [(i, int(j)) for j in near if forest.join(i, int(j))]
    return found


def _links(radius: int):
    refs = references()

    def groups(batches):
        """Members of each key from sorted rows."""
        held_key, held = None, []
        for batch in batches:
            if not batch.num_rows:
                continue
            keys = np.stack([batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("pair", "left", "right", "part")], axis=1)
            fp = batch.column(batch.schema.get_field_index("fp")).to_numpy().view(np.uint64)
            cuts = np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1
            for a, b in zip([0, *cuts], [*cuts, len(fp)]):
                key = tuple(keys[a])
                if key != held_key:
                    if len(held) and sum(map(len, held)) > 1:
                        yield np.concatenate(held)
                    held_key, held = key, []
                held.append(fp[a:b])
        if len(held) and sum(map(len, held)) > 1:
            yield np.concatenate(held)

    def run(batches):
        left, right = [], []

        def out():
            return pa.RecordBatch.from_arrays([pa.array(np.array(x, dtype=np.uint64).view(np.int64)) for x in (left, right)], names=["a", "b"])

        for members in groups(batches):
            for i, j in linked(members, radius, refs):
                left.append(members[i])
                right.append(members[j])
            if len(left) > 50_000:
                yield out()
                left, right = [], []
        if left:
            yield out()

    return run


def fingerprint_links(fps: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Links (``a``, ``b``) that connect the distinct values of column ``fp`` as all
    links of at most ``radius`` bits do."""
    if not 0 <= radius <= len(BLOCKS) - 2:
        raise ValueError("a radius above 4 leaves fewer than two of six blocks alone")
    keys = fps.select("fp").mapInArrow(tidied(_table()), "pair int, left bigint, right bigint, fp bigint")
    shared = ["pair", "left", "right"]
    sizes = keys.groupBy(*shared).count().where("count > 1")
    crowded = keys.join(sizes, shared)
    parts = F.ceil(F.col("count") / F.lit(KEY_LIMIT)).cast("int")
    own = F.pmod(F.xxhash64("fp"), F.col("parts")).cast("int")
    meets = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda o: F.least(o, F.col("own")) * F.col("parts") + F.greatest(o, F.col("own")))
    dealt = crowded.withColumn("parts", parts).withColumn("own", own).withColumn("part", F.explode(meets))
    dealt = dealt.select(*shared, "part", "fp").repartition(*shared, "part").sortWithinPartitions(*shared, "part", "fp")
    return dealt.mapInArrow(tidied(_links(radius)), "a bigint, b bigint").distinct()


def components(links: DataFrame, ids: DataFrame) -> DataFrame:
    """The smallest ``id`` reachable over ``links`` (``a``, ``b``) from every node
    that has a link. ``ids``: ``fp``, ``id``. Rounds of hooking to the smallest neighbour and
    of path halving; each is written out, so the plan stays small and a lost executor costs one round."""
    both = stage(links.union(links.select("b", "a")).toDF("a", "b"), "both")
    named = ids.select(F.col("fp").alias("b"), F.col("id").alias("b_id"))
    start = hot_join(both, named, "b").select("a", "b_id")
    edges = stage(hot_join(start, ids.select(F.col("fp").alias("a"), F.col("id").alias("a_id")), "a").select(F.col("a_id").alias("a"), F.col("b_id").alias("b")).distinct(), "links")
    del both, named, start
    release(edges.sparkSession)
    hubs = hot_keys(edges, "b")
    label = stage(edges.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("label")), "label")
    while True:
        seen = hot_join(edges, label.select(F.col("a").alias("b"), F.col("label").alias("b_label")), "b", hot=hubs, known=True)
        near = seen.groupBy("a").agg(F.min("b_label").alias("near"))
        hooked = label.join(near, "a").select("a", F.col("label").alias("old"), F.least("label", "near").alias("label"))
        # smaller labels also reach the node that was the label so far
        told = hooked.groupBy(F.col("old").alias("a")).agg(F.min("label").alias("told"))
        lower = stage(hooked.join(told, "a", "left").select("a", "old", F.least("label", "told").alias("label")), "lower")
        if lower.where("old <> label").isEmpty():
            return lower.select("a", "label")
        up = lower.select(F.col("a").alias("label"), F.col("label").alias("further"))
        label = stage(hot_join(lower, up, "label", "left").select("a", F.least("label", "further").alias("label")), "label")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, radius: int = RADIUS) -> DataFrame:
    """``doc_id, fingerprint, component_id`` for each input row."""
    d = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("binary").alias("text"))
    rows = stage(d.mapInArrow(tidied(_fingerprints(shingle)), "doc_id bigint, fp bigint"), "fingerprints")
    classes = stage(rows.groupBy("fp").agg(F.min("doc_id").alias("known"), F.count(F.lit(1)).alias("n")), "classes")
    # a class of null ids only gets a stand-in above all ids, by its fingerprint
    ids = classes.select("fp", F.struct(F.col("known").isNull().alias("none"), F.coalesce("known", "fp").alias("v")).alias("id"))
    found = components(fingerprint_links(classes, radius), ids)
    table = ids.join(found, ids["id"] == found["a"], "left").select("fp", F.coalesce("label", "id").alias("c"))
    component = table.select("fp", F.when(~F.col("c.none"), F.col("c.v")).alias("component_id"))
    named = hot_join(rows, component, "fp")
    return named.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
