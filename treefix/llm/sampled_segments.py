"""Distinct sampled segmentations under a public piece vocabulary, without replacement.

Every text spans a lattice of pieces. Its segmentations get log probabilities from unigram piece
weights (``-exponent * log(rank + offset)`` of the piece's rank in the vocabulary file, normalised over the
lattice by backward sums). Adding an independent Gumbel value to each segmentation and taking the
k largest is sampling without replacement. The largest perturbed value below any prefix
can be drawn top down: the root's first; the child that keeps it is drawn by its share, and the other children's values are
Gumbel values cut off at it. A best-first search over prefixes by that value therefore emits the sample in order, and
expands little beside the k paths. The next value in the queue is the threshold for the inclusion scores.

Many texts are searched at once, in arrays: distinct chunks are compiled together, a place of all paths is drawn at a time.
The edges beside a path's unlikely end are a group, whose largest value is drawn first; only if it enters the queue are they drawn one by one, given it.

Each row's draws are hashes of its key, the emission, the place and the edge, so results do not depend on partitions, batches or
retries. Null and empty texts have one empty segmentation. Texts with fewer than k segmentations yield all, with inclusion 1.
Rows of equal key and text yield equal samples. A space mark that a text itself holds is encoded by its bytes, so decoding gives the text back.
A text is held whole: some 100 bytes for each character.
"""

from __future__ import annotations

import functools
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from treefix.llm.shared import mixed, rows_of, tidied

MODEL, SAMPLES, EXPONENT, OFFSET, CHARS = "piece_bpe_32k.model", 4, 2.0, 10.0, 500_000
SPACE = "▁"
MARK, OWN_MARK = ord(SPACE), 0x110000  # the second, beyond all characters, stands for a mark that is part of the text
_STEP = np.uint64(0x9E3779B97F4A7C15)
EARLY = -8.0  # up to this log probability the edges beside a path are drawn one by one


def model_path(name: str = MODEL) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def codes_of(texts: list[str]) -> np.ndarray:
    return np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), dtype="<u4")


def ranges(first: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """All of ``first .. first + size`` one after another."""
    ends = np.cumsum(sizes)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(first - ends + sizes, sizes)


def walked(h: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Hashes of strings that are longer by one character."""
    with np.errstate(over="ignore"):
        return mixed(h ^ ((codes.astype(np.uint64) + np.uint64(1)) * _STEP))


def uniform(seed: np.ndarray, emission: int, place: np.ndarray, edge: np.ndarray | int) -> np.ndarray:
    """Numbers between 0 and 1, neither included, by what they are for."""
    with np.errstate(over="ignore"):
        z = seed + np.uint64(emission + 1) * np.uint64(0xD1B54A32D192ED03) + place.astype(np.uint64) * np.uint64(0xABC98388FB8FAC03) + np.asarray(edge, dtype=np.uint64) * np.uint64(0x8CB92BA72F3D8DD7)
        return (mixed(mixed(z) ^ _STEP) >> np.uint64(11)).astype(np.float64) * 2.0**-53 + 2.0**-54


def cut_off(location: np.ndarray, most: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Gumbel values at ``location``, given that they are at most ``most``."""
    return location - np.logaddexp(location - most, np.log(-np.log(u)))


@dataclass
class Compiled:
    """Lattices of chunks. A node is a place of a chunk; its edges lie side by side."""

    end: np.ndarray  # of a node's chunk
    first: np.ndarray
    degree: np.ndarray
    piece: np.ndarray  # of an edge: its id, or minus one minus the character that stands for its bytes
    size: np.ndarray
    share: np.ndarray  # log
    upto: np.ndarray  # the node's shares so far


@dataclass
class Paths:
    """A path for each text: places, nodes and edges, and the log probability before each."""

    place: np.ndarray
    node: np.ndarray
    edge: np.ndarray
    before: np.ndarray
    cuts: np.ndarray
    total: np.ndarray


class Lattice:
    """Pieces as a table of prefix hashes, and their weights.

    No piece runs from other characters into a space mark, so chunks (space marks, then
    others) have lattices of their own and a text's lattice is their sequence."""

    def __init__(self, path: str, exponent: float = EXPONENT):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        self.bytes = np.array([sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)])
        self.raw = [b""] * sp.get_piece_size()
        for b, i in enumerate(self.bytes):
            self.raw[i] = bytes([b])
        own, known = {}, 0
        for i in range(sp.get_piece_size()):
            if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i)):
                text, known = sp.id_to_piece(i), known + 1
                self.raw[i] = text.replace(SPACE, " ").encode()
                if not re.search(f"[^{SPACE}]{SPACE}", text):
                    own[text] = i
        self.byte_weight = -exponent * float(np.log(known + OFFSET))
        names = sorted(own, key=len)
        sizes = np.array([len(x) for x in names])
        self.longest = int(sizes.max(initial=1))
        codes, begin, ids = codes_of(names), np.cumsum(sizes) - sizes, np.array([own[x] for x in names])
        h, left = np.zeros(len(names), np.uint64), np.arange(len(names))
        prefixes, whole = [], {}
        for n in range(1, self.longest + 1):
            left = left[sizes[left] >= n]
            h[left] = walked(h[left], codes[begin[left] + n - 1])
            prefixes.append(np.unique(h[left]))
            whole |= dict(zip(h[left[sizes[left] == n]].tolist(), ids[left[sizes[left] == n]].tolist()))
        self.prefixes = np.unique(np.concatenate(prefixes))
        self.id_of = np.array([whole.get(x, -1) for x in self.prefixes.tolist()], dtype=np.int64)
        self.weight_of = -exponent * np.log(np.maximum(self.id_of, 0) + OFFSET)

    def compiled(self, codes: np.ndarray, begin: np.ndarray, sizes: np.ndarray) -> Compiled:
        """The lattices of chunks that lie side by side in ``codes``."""
        n = len(codes)
        end = np.repeat(begin + sizes, sizes)
        at, h = np.arange(n), np.zeros(n, np.uint64)
        source, size, piece, weight = [], [], [], []
        for length in range(1, self.longest + 1):
            inside = at + length <= end[at]
            at, h = at[inside], walked(h[inside], codes[at[inside] + length - 1])
            found = np.minimum(np.searchsorted(self.prefixes, h), len(self.prefixes) - 1)
            known = self.prefixes[found] == h
            if length == 1:  # a character that no piece is: its bytes
                alone = np.flatnonzero(~(known & (self.id_of[found] >= 0)))
                code = np.where(codes[alone] == OWN_MARK, MARK, codes[alone]).astype(np.int64)
                source.append(alone)
                size.append(np.ones(len(alone), np.int64))
                piece.append(-1 - code)
                weight.append(self.byte_weight * (1 + (code >= 0x80) + (code >= 0x800) + (code >= 0x10000)))
            at, h, found = at[known], h[known], found[known]
            if not len(at):
                break
            is_piece = self.id_of[found] >= 0
            source.append(at[is_piece])
            size.append(np.full(int(is_piece.sum()), length))
            piece.append(self.id_of[found[is_piece]])
            weight.append(self.weight_of[found[is_piece]])
        source, size, piece, weight = (np.concatenate(x) for x in (source, size, piece, weight))
        # nodes by how far from their chunk's end, so that sums from the end take a distance at a time
        left = end - np.arange(n)
        order = np.argsort(left, kind="stable")
        rank = np.empty(n, np.int64)
        rank[order] = np.arange(n)
        by = np.argsort(rank[source], kind="stable")
        source, size, piece, weight = source[by], size[by], piece[by], weight[by]
        degree = np.bincount(source, minlength=n)
        offset = np.concatenate([[0], np.cumsum(degree[order])])
        target = source + size
        ends = target == end[source]
        target[ends] = 0
        back = np.zeros(n)
        cuts = np.concatenate([[0], np.cumsum(np.bincount(left)[1:])])
        for low, high in zip(cuts[:-1], cuts[1:]):
            a, b = offset[low], offset[high]
            v = weight[a:b] + np.where(ends[a:b], 0.0, back[target[a:b]])
            starts, many = offset[low:high] - a, degree[order[low:high]]
            top = np.maximum.reduceat(v, starts)
            total = np.log(np.add.reduceat(np.exp(v - np.repeat(top, many)), starts)) + top
            back[order[low:high]] = total
            weight[a:b] = v - np.repeat(total, many)
        upto = np.exp(weight)  # summed node by node, so that no other chunk changes a rounding
        starts, many = offset[:-1], degree[order]
        for k in range(1, int(many.max(initial=1))):
            on = starts[many > k] + k
            upto[on] += upto[on - 1]
        return Compiled(end, offset[:-1][rank], degree, piece, size, weight, upto)

    def sample(self, text: str | None, k: int, seed: int) -> list[tuple[np.ndarray, float, float, float]]:
        return self.sample_all([text], np.array([seed], np.uint64), k)[0]

    def sample_all(self, texts: list[str | None], seeds: np.ndarray, k: int) -> list[list[tuple[np.ndarray, float, float, float]]]:
        """For each text at most k of (ids, log probability, perturbed value, inclusion score), best first."""
        out: list[list] = [[(np.zeros(0, np.int64), 0.0, 0.0, 1.0)] for _ in texts]
        full = [i for i, t in enumerate(texts) if t]
        if not full:
            return out
        seeds = seeds[full]
        sizes = np.array([len(texts[i]) + 1 for i in full])
        ends = np.cumsum(sizes)
        start = ends - sizes
        codes = codes_of([" " + texts[i] for i in full]).copy()
        codes[codes == MARK] = OWN_MARK
        codes[codes == 32] = MARK
        mark = codes == MARK
        opens = mark.copy()
        opens[1:] &= ~mark[:-1]
        opens[start] = True
        chunk_at = np.flatnonzero(opens)
        chunk_size = np.diff(np.append(chunk_at, len(codes)))
        # equal chunks are compiled once
        with np.errstate(over="ignore"):
            power = np.cumprod(np.full(int(chunk_size.max()), _STEP | np.uint64(1)))
            local = np.arange(len(codes)) - np.repeat(chunk_at, chunk_size)
            names = mixed(np.add.reduceat(mixed(codes.astype(np.uint64) + _STEP) * power[local], chunk_at) + chunk_size.astype(np.uint64))
        del local, opens, mark
        _, one, which = np.unique(names, return_index=True, return_inverse=True)
        own_size = chunk_size[one]
        own_begin = np.cumsum(own_size) - own_size
        net = self.compiled(codes[ranges(chunk_at[one], own_size)], own_begin, own_size)
        node_at = own_begin[which]
        last_chunk = np.searchsorted(chunk_at, ends)
        doc_of = np.repeat(np.arange(len(full)), np.diff(last_chunk, prepend=0))
        del codes, names

        def drawn(emission: int, place: np.ndarray, node: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, ...]:
            """Paths from the given places to the ends of their chunks, in order of place."""
            found = []
            while len(place):
                edge = net.first[node]
                several = np.flatnonzero(net.degree[node] > 1)
                u = uniform(seeds[doc[several]], emission, place[several] - start[doc[several]], 0)
                last = net.first[node[several]] + net.degree[node[several]] - 1
                while len(several):
                    on = np.flatnonzero((u >= net.upto[edge[several]]) & (edge[several] < last))
                    several, u, last = several[on], u[on], last[on]
                    edge[several] += 1
                found.append((place, node, edge, doc))
                more = node + net.size[edge] < net.end[node]
                place, node, doc = (place + net.size[edge])[more], (node + net.size[edge])[more], doc[more]
            if not found:
                return tuple(np.zeros(0, np.int64) for _ in range(4))
            place, node, edge, doc = (np.concatenate(x) for x in zip(*found))
            order = np.argsort(place, kind="stable")
            return place[order], node[order], edge[order], doc[order]

        queue: list[list[tuple[float, float, int, int, int]]] = [[] for _ in full]  # (value, log probability, emission, path's node, edge)
        emitted: list[Paths] = []
        value = -np.log(-np.log(uniform(seeds, -1 & 0xFFFF, np.zeros(len(full)), 0)))
        found: list[list[tuple[np.ndarray, float, float]]] = [[] for _ in full]
        here = np.arange(len(full))  # texts that emit in this turn
        for emission in range(k):
            if emission == 0:
                place, node, edge, doc = drawn(0, chunk_at, node_at, doc_of)
                base, kept = np.zeros(len(full)), [None] * len(full)
            else:
                here = np.array([d for d in here if queue[d]], dtype=np.int64)
                if not len(here):
                    break
                taken = [queue[d].pop(0) for d in here]
                value, base, kept = np.zeros(len(full)), np.zeros(len(full)), [None] * len(full)
                value[here], base[here] = [t[0] for t in taken], [t[1] for t in taken]
                at = np.array([emitted[t[2]].place[t[3]] for t in taken])
                on = np.array([emitted[t[2]].node[t[3]] for t in taken])
                by = np.array([t[4] for t in taken])
                for d, t in zip(here, taken):
                    kept[d] = t[2:]
                nxt, inside = at + net.size[by], on + net.size[by] < net.end[on]
                following = np.searchsorted(chunk_at, at, side="right")
                count = last_chunk[here] - following
                rest = ranges(following, count)
                starts = np.concatenate([nxt[inside], chunk_at[rest]]), np.concatenate([(on + net.size[by])[inside], node_at[rest]]), np.concatenate([here[inside], np.repeat(here, count)])
                place, node, edge, doc = drawn(emission, *starts)
            share = net.share[edge]
            cuts = np.searchsorted(doc, np.arange(len(full) + 1))
            sums = np.concatenate([[0.0], np.cumsum(share)])
            # sums of each text from its own first node on, so that texts don't share rounding
            before = np.empty(len(share))
            for d in here:
                a, b = cuts[d], cuts[d + 1]
                before[a:b] = base[d] + np.concatenate([[0.0], np.cumsum(share[a : b - 1])]) if b > a else 0.0
            del sums
            total = base.copy()
            ends_here = cuts[1:] > cuts[:-1]
            total[ends_here] = before[cuts[1:][ends_here] - 1] + share[cuts[1:][ends_here] - 1]
            parts, new_cuts = {"place": [], "node": [], "edge": [], "before": []}, np.zeros(len(full) + 1, np.int64)
            shift = np.zeros(len(full), np.int64)  # where a text's new nodes begin in its path
            for d in range(len(full)):
                length = 0
                a, b = cuts[d], cuts[d + 1]
                if kept[d] is not None:
                    parent, index, branch = kept[d]
                    old = emitted[parent]
                    c = old.cuts[d]
                    for name in parts:
                        parts[name].append(getattr(old, name)[c : index + 1])
                    parts["edge"][-1] = np.append(parts["edge"][-1][:-1], branch)
                    length = index + 1 - c
                shift[d] = new_cuts[d] + length
                for name, held in (("place", place), ("node", node), ("edge", edge), ("before", before)):
                    parts[name].append(held[a:b])
                new_cuts[d + 1] = new_cuts[d] + length + b - a
            path = Paths(*(np.concatenate(parts[n]) for n in ("place", "node", "edge", "before")), new_cuts, total)
            emitted.append(path)
            ids, begin = self.expanded(net.piece[path.edge])
            for d in here:
                found[d].append((ids[begin[new_cuts[d]] : begin[new_cuts[d + 1]]], float(total[d]), float(value[d])))

            def others(rows: np.ndarray, most: np.ndarray, first: bool) -> None:
                """Draws the values of the edges beside the path at the given new nodes, at most ``most`` by text, and keeps each
                text's k + 1 best. Unless these are a text's ``first`` ones, the largest of a text's is known to be ``most``."""
                rows = rows[net.degree[node[rows]] > 1]
                many = net.degree[node[rows]]
                edges, at = ranges(net.first[node[rows]], many), np.repeat(rows, many)
                beside = edges != edge[at]
                edges, at = edges[beside], at[beside]
                own, location = doc[at], before[at] + net.share[edges]
                v = cut_off(location, most[own], uniform(seeds[own], emission, place[at] - start[own], 1 + edges - net.first[node[at]]))
                if not first:
                    for d in np.unique(own).tolist():
                        a, b = np.searchsorted(own, [d, d + 1])
                        share = np.cumsum(np.exp(location[a:b] - location[a:b].max()))
                        u = uniform(seeds[d : d + 1], emission, np.zeros(1), (1 << 62) + 1)[0]
                        v[a + min(int(np.searchsorted(share, u * share[-1])), b - a - 1)] = most[d]
                order = np.lexsort((edges, at, -v, own))
                own, v, location, at, edges = (x[order] for x in (own, v, location, at, edges))
                best = np.arange(len(own)) - np.searchsorted(own, own) < k + 1
                at = at[best] - cuts[own[best]] + shift[own[best]]
                for d, *entry in zip(own[best].tolist(), v[best].tolist(), location[best].tolist(), [emission] * int(best.sum()), at.tolist(), edges[best].tolist()):
                    queue[d].append(tuple(entry))
                for d in np.unique(own).tolist():
                    queue[d].sort(key=lambda x: (-x[0], x[2:]))
                    del queue[d][k + 1 :]

            early = before > EARLY
            others(np.flatnonzero(early), value, True)
            late = np.flatnonzero(~early)
            if len(late):
                tail, first = np.unique(doc[late], return_index=True)
                top = before[late[first]]  # of all paths through the first late node; the path itself is none of the others
                with np.errstate(divide="ignore"):
                    mass = top + np.log(-np.expm1(np.minimum(total[tail] - top, 0.0)))
                group = np.full(len(full), -np.inf)
                some = mass > -np.inf
                group[tail[some]] = cut_off(mass[some], value[tail[some]], uniform(seeds[tail[some]], emission, np.zeros(int(some.sum())), 1 << 62))
                floor = np.array([q[k][0] if len(q) > k else -np.inf for q in queue])
                enters = group > floor
                others(late[enters[doc[late]]], group, False)
        for d, i in enumerate(full):
            threshold = queue[d][0][0] if queue[d] else -np.inf
            out[i] = [(ids, phi, v, 1.0 if threshold == -np.inf else float(-np.expm1(-np.exp(min(phi - threshold, 700.0))))) for ids, phi, v in found[d]]
        return out

    def expanded(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids with those of the bytes of characters that no piece is, and where each given one begins (and the last ends)."""
        at = np.flatnonzero(ids < 0)
        if not len(at):
            return ids, np.arange(len(ids) + 1)
        own, which = np.unique(-1 - ids[at], return_inverse=True)
        raw = [self.bytes[list(chr(c).encode("utf-8", "surrogatepass"))] for c in own.tolist()]
        sizes = np.ones(len(ids), np.int64)
        sizes[at] = np.array([len(x) for x in raw])[which]
        out = np.repeat(ids, sizes)
        begin = np.concatenate([[0], np.cumsum(sizes)])
        for n in range(max(map(len, raw))):
            table = np.array([x[n] if n < len(x) else -1 for x in raw])[which]
            longer = table >= 0
            out[begin[at[longer]] + n] = table[longer]
        return out, begin

    def decode(self, ids: list[int]) -> str:
        """The text of a segmentation."""
        return b"".join(map(self.raw.__getitem__, ids)).decode(errors="replace").removeprefix(" ")


@functools.lru_cache(maxsize=2)
def lattice(path: str, exponent: float) -> Lattice:
    return Lattice(path, exponent)


def sample_segmentations(rows: DataFrame, key_cols: list[str], text_col: str = "text", k: int = SAMPLES, seed: int = 42, path: str | None = None, exponent: float = EXPONENT) -> DataFrame:
    """The key columns and, for each of at most k samples: ``rank, ids, log_prob, perturbed, inclusion``."""
    place = path or model_path()
    d = rows.select(*[F.col(c).cast("string").alias(f"k{n}") for n, c in enumerate(key_cols)], F.xxhash64(F.lit(seed), *[F.col(c) for c in key_cols]).alias("row_key"), F.col(text_col).alias("text"))
    keys = [f"k{n}" for n in range(len(key_cols))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, held, size = lattice(place, exponent), [], 0

        def flush() -> pa.RecordBatch:
            seeds = np.array([r[-2] & (1 << 64) - 1 for r in held], dtype=np.uint64)
            samples = own.sample_all([r[-1] for r in held], seeds, k)
            rows = [(*r[:-2], n + 1, *s) for r, found in zip(held, samples) for n, s in enumerate(found)]
            *named, rank, ids, log_prob, perturbed, inclusion = zip(*rows)
            ends = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(ids).astype(np.int32)))
            kinds = [*[pa.string()] * len(keys), pa.int32()]
            return pa.RecordBatch.from_arrays([*(pa.array(c, t) for c, t in zip((*named, rank), kinds)), lists, *(pa.array(c, pa.float64()) for c in (log_prob, perturbed, inclusion))], names=[*keys, "rank", "ids", "log_prob", "perturbed", "inclusion"])

        for row in rows_of(batches, *keys, "row_key", "text"):
            held.append(row)
            size += len(row[-1] or "") + 1
            if size >= CHARS or len(held) >= 4096:
                yield flush()
                held, size = [], 0
        if held:
            yield flush()

    schema = ", ".join(f"{c} string" for c in keys) + ", rank int, ids array<int>, log_prob double, perturbed double, inclusion double"
    found = d.mapInArrow(tidied(run), schema)
    named = [F.col(f"k{n}").cast(rows.schema[c].dataType).alias(c) for n, c in enumerate(key_cols)]
    return found.select(*named, "rank", "ids", "log_prob", "perturbed", "inclusion")


def decode_segmentations(found: DataFrame, ids_col: str = "ids", path: str | None = None, exponent: float = EXPONENT) -> DataFrame:
    """The rows of ``found`` with ``decoded``, the text of their ids."""
    place, names = path or model_path(), found.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = lattice(place, exponent)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                text = [None if ids is None else own.decode(ids) for (ids,) in rows_of(iter([part]), ids_col)]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(text, pa.string())], names=[*names, "decoded"])

    return found.mapInArrow(tidied(run), T.StructType([*found.schema.fields, T.StructField("decoded", T.StringType())]))
