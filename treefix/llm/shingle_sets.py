"""Near duplicates by similarity of word shingle sets.

Two texts link if the Jaccard similarity of their sets of word shingles is ``SIMILARITY`` or more.

Search. Texts that the SimHash operator links by their fingerprints, directly or over others, are candidates, as all texts of
such a component share its key. Fingerprints reach only texts that are nearly identical, so for the others ``BANDS`` band keys of ``ROWS`` min-hashes
each stand for a set too; sets that share a key are candidates. A pair at similarity s shares a band key with probability
``1 - (1 - s ** ROWS) ** BANDS``, which is above 0.9999 at 0.8 and rises with s. Whole sets decide on every candidate. First every set is checked against one other of a key. Keys whose members are then still in different
components, and what such keys connect, form groups; a group's sets meet in a task, which checks all of its pairs in different
components through an index of their shingles and gives back a spanning forest, so rows out never exceed rows in. Groups of over
``GROUP_ROWS`` sets or ``GROUP_HASHES`` shingles are dealt to several tasks, a pair of parts each, which still compares all members.

Equal sets are one node; texts without words have the empty set. Rows with a null id
have the smallest known id of their component (null if there is none). Repeated rows are returned as often as they occur.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.llm import simhash_pivots
from treefix.llm.shared import as_bytes, hot_join, hot_keys, release, rows_of, salted_join, stage, tidied
from treefix.llm.simhash_pivots import components

SHINGLE, SIMILARITY, BANDS, ROWS = 5, 0.8, 24, 5
GROUP_ROWS, GROUP_HASHES = 2048, 1 << 20
PART = 4096
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_DRAWN = np.random.default_rng(5).integers(0, 1 << 64, (2, BANDS * ROWS, 1), dtype=np.uint64)
_FACTOR, _OFFSET = _DRAWN[0] | np.uint64(1), _DRAWN[1]


def shingle_set(text: bytes | None, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles; a shorter text is one shingle."""
    words = as_bytes(text).translate(_LOWER).split()
    if not words:
        return np.zeros(0, dtype="<u8")
    size = min(shingle, len(words))
    shifted = zip(*(words[k:] for k in range(size)))
    return np.unique(np.fromiter((xxhash.xxh64_intdigest(b" ".join(s), 42) for s in shifted), dtype="<u8", count=len(words) - size + 1))


def node_of(own: np.ndarray) -> int:
    """The signed number of a set."""
    return int(np.uint64(xxhash.xxh64_intdigest(own.tobytes(), 42)).view(np.int64))


def band_keys(own: np.ndarray) -> np.ndarray:
    """A key for each band; none for the empty set."""
    if not len(own):
        return np.zeros(0, dtype=np.int64)
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, dtype=np.uint64)
    for at in range(0, len(own), PART):
        least = np.minimum(least, (own[at : at + PART][None, :] * _FACTOR + _OFFSET).min(axis=1))
    key = np.arange(1, BANDS + 1, dtype=np.uint64)
    for row in least.reshape(BANDS, ROWS).T:
        key = (key ^ row) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    return key.view(np.int64)


def _sketches(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = []

        def flush() -> pa.RecordBatch:
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()))
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=["doc_id", "th", "node", "bands"])

        for doc_id, th, text in rows_of(batches, "doc_id", "th", "text"):
            own = shingle_set(text, shingle)
            out.append((doc_id, th, node_of(own), band_keys(own)))
            if len(out) == 2048:
                yield flush()
                out = []
        if out:
            yield flush()

    return run


def _sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nodes, held, size = [], [], 0

        def flush() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(held, pa.list_(pa.int64()))], names=["node", "held"])

        for (text,) in rows_of(batches, "text"):
            own = shingle_set(text, shingle)
            nodes.append(node_of(own))
            held.append(own.view(np.int64))
            size += len(own)
            if size > 100_000:
                yield flush()
                nodes, held, size = [], [], 0
        if nodes:
            yield flush()

    return run


def _alike(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """Of the pairs of nodes (one for each ``b``) those whose sets are similar enough."""
    left, right = sets.toDF("a", "a_held"), sets.toDF("b", "b_held")
    both = F.size(F.array_intersect("a_held", "b_held"))
    met = salted_join(pairs, left, "a", "b", hot_keys(pairs, "a")).join(right, "b")
    return met.where(both / (F.size("a_held") + F.size("b_held") - both) >= similarity).select("a", "b")


def forest(sets: list[np.ndarray], component: np.ndarray, similarity: float) -> list[tuple[int, int]]:
    """Pairs of sets that are similar enough and connect all that such pairs connect, beyond the components they are in."""
    names, own = np.unique(component, return_inverse=True)
    up, left, found = list(range(len(names))), len(names), []

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = x = up[up[x]]
        return x

    sizes = np.array([len(x) for x in sets])
    every = np.concatenate(sets)
    _, number = np.unique(every, return_inverse=True)
    order = np.argsort(number, kind="stable")
    holders = np.repeat(np.arange(len(sets)), sizes)[order]
    many = np.bincount(number) if len(number) else np.zeros(0, dtype=np.int64)
    first, ends = np.cumsum(many) - many, np.cumsum(sizes)
    for i in range(len(sets)):
        if left == 1:
            break
        mine = number[ends[i] - sizes[i] : ends[i]]
        mine = mine[many[mine] > 1]
        lengths = many[mine]
        stops = np.cumsum(lengths)
        places = np.arange(stops[-1] if len(stops) else 0) + np.repeat(first[mine] - stops + lengths, lengths)
        shared = np.bincount(holders[places], minlength=len(sets))
        near = np.flatnonzero((shared / np.maximum(sizes[i] + sizes - shared, 1) >= similarity) & (own != own[i]))
        for j in near.tolist():
            x, y = root(int(own[i])), root(int(own[j]))
            if x != y:
                up[max(x, y)] = min(x, y)
                left -= 1
                found.append((i, j))
    return found


def _forests(similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, []

        def pairs() -> pa.RecordBatch:
            found = forest([s for _, _, s in held], np.array([c for _, c, _ in held]), similarity) if len(held) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array([held[p[side]][0] for p in found], pa.int64()) for side in (0, 1)], names=["a", "b"])

        for batch in batches:
            names = {n: batch.column(batch.schema.get_field_index(n)) for n in ("part", "node", "component", "held")}
            groups = batch.column(batch.schema.get_field_index("crowd")).to_pylist()
            sets = names["held"]
            ends, values = sets.offsets.to_numpy(), sets.values.to_numpy(zero_copy_only=False)
            for i, (g, part, node, component) in enumerate(zip(groups, *(names[n].to_pylist() for n in ("part", "node", "component")))):
                if (g, part) != key:
                    yield pairs()
                    key, held = (g, part), []
                held.append((node, component, values[ends[i] : ends[i + 1]].copy()))
        yield pairs()

    return run


def _group_links(placed: DataFrame, sets: DataFrame, ids: DataFrame, similarity: float) -> DataFrame:
    """Links between the components of nodes that keys (``key``, ``node``, ``c``) bring together."""
    heads = placed.groupBy("key").agg(F.min("node").alias("a"))
    beside = hot_join(placed, heads, "key").where("a <> node").select("a", F.col("node").alias("b")).distinct()
    crowd = _labelled(stage(beside, "beside"), ids).select("node", F.xxhash64("c").alias("crowd"))
    members = placed.select("node", F.xxhash64("c").alias("component")).distinct().join(crowd, "node")
    sized = stage(members.join(sets.select("node", F.size("held").alias("hashes")), "node"), "members")
    totals = sized.groupBy("crowd").agg(F.count(F.lit(1)).alias("rows"), F.sum("hashes").alias("all"))
    parts = F.greatest(F.ceil(F.col("rows") / GROUP_ROWS), F.ceil(F.col("all") / GROUP_HASHES), F.lit(1)).cast("int")
    dealt = hot_join(sized, totals.select("crowd", parts.alias("parts")), "crowd")
    dealt = dealt.withColumn("own", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    meets = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda o: F.least(o, F.col("own")) * F.col("parts") + F.greatest(o, F.col("own")))
    rows = dealt.join(sets, "node").select("crowd", F.explode(meets).alias("part"), "node", "component", "held")
    met = rows.repartition("crowd", "part").sortWithinPartitions("crowd", "part")
    return met.mapInArrow(tidied(_forests(similarity)), "a bigint, b bigint")


def _labelled(links: DataFrame, ids: DataFrame) -> DataFrame:
    """``node, c``: the smallest id of each node's component."""
    found = components(links, ids)
    return ids.join(found, ids["id"] == found["a"], "left").select(F.col("fp").alias("node"), F.coalesce("label", "id").alias("c"))


def fingerprint_keys(d: DataFrame, rows: DataFrame) -> DataFrame:
    """``node, key``: nodes of different texts whose fingerprints are linked share their component as a key."""
    named = simhash_pivots.near_duplicates(d.select("th", "text"), "th").where("doc_id <> component_id")
    linked = stage(named.select(F.col("doc_id").alias("th"), F.col("component_id").alias("key")).distinct(), "linked_texts")
    every = linked.unionByName(linked.select(F.col("key").alias("th"), "key").distinct())
    return every.join(rows.select("th", "node").distinct(), "th").select("node", "key").distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, similarity: float = SIMILARITY, bands: int = BANDS) -> DataFrame:
    """``doc_id, component_id`` for each input row. ``bands``: how many band keys of a set are used beside its fingerprints' links."""
    d = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("binary").alias("text")).withColumn("th", F.xxhash64("text"))
    rows = stage(d.mapInArrow(tidied(_sketches(shingle)), "doc_id bigint, th bigint, node bigint, bands array<bigint>"), "sketches")
    classes = stage(rows.groupBy("node").agg(F.min("doc_id").alias("known"), F.min("th").alias("th")), "classes")
    # a class of null ids only gets a stand-in above all ids, by its number
    ids = classes.select(F.col("node").alias("fp"), F.struct(F.col("known").isNull().alias("none"), F.coalesce("known", "node").alias("v")).alias("id"))

    banded = rows.dropDuplicates(["node"]).select("node", F.explode(F.slice("bands", 1, bands)).alias("key"))
    keys = stage(banded.unionByName(fingerprint_keys(d, rows)), "keys")
    release(docs.sparkSession)
    shared = keys.groupBy("key").agg(F.min("node").alias("first"), F.max("node").alias("last")).where("first <> last")
    crowded = stage(hot_join(keys, shared, "key").select("key", "node", "first"), "crowded")
    wanted = classes.join(crowded.select("node").distinct(), "node", "left_semi").select(F.col("th").alias("own"))
    texts = stage(d.join(wanted, d["th"] == wanted["own"], "left_semi").dropDuplicates(["th"]).select("text"), "texts")
    sets = stage(texts.mapInArrow(tidied(_sets(shingle)), "node bigint, held array<bigint>"), "sets")

    starred = stage(crowded.where("node <> first").groupBy(F.col("node").alias("b")).agg(F.min("first").alias("a")).select("a", "b"), "starred")
    links = stage(_alike(starred, sets, similarity), "first_links")
    release(docs.sparkSession)  # shuffle files behind what is staged
    table = stage(_labelled(links, ids), "first_components")
    placed = stage(crowded.select("key", "node").join(table, "node"), "placed")
    apart = placed.groupBy("key").agg(F.min("c").alias("low"), F.max("c").alias("high")).where("low <> high").select("key")
    placed = stage(hot_join(placed, apart, "key"), "apart")
    release(docs.sparkSession)
    if not placed.isEmpty():
        table = _labelled(stage(links.unionByName(_group_links(placed, sets, ids, similarity)), "set_links"), ids)
    component = table.select("node", F.when(~F.col("c.none"), F.col("c.v")).alias("component_id"))
    return hot_join(rows.select("doc_id", "node"), component, "node").select("doc_id", "component_id")
