"""Exact Jaccard join of documents by metric-space recursion.

A document is the set of its distinct word shingles; two link when the Jaccard distance of their sets is at most
eps = 1 - threshold. Distances between unrelated texts are all 1, so whole-space Voronoi cells around sampled documents would
tie everywhere. The first level's pivots are therefore single shingles: all shingles have one order, rare ones first, a linked pair shares an
element among the first n - ceil(t n) + 1 of either set, and a document goes to the regions of those. Shingles are counted over all documents
exactly, by their 32-bit codes in each of many tasks, and only those that two documents hold are sent back: the others come first in their document's
order and have no region, so a document with enough text of its own has none at all. (Shingles whose codes meet count as one; that adds
members to regions and loses none.)

A region is dropped when the shingle before its own is the same one in all its members, for they meet in that shingle's region
already. What is left is cut where sorted set sizes leap by more than linked sets may differ, and joined with documents as
pivots. A document that no pivot has taken yet becomes the next pivot p and is compared with all others of the region; of these stay

* the cell of p: who may link with p, and, if any document may, who may be within 2 eps of it;
* the remainder: who may link with no pivot.

By the triangle inequality two documents within eps meet again: if either links with a pivot, the other is within 2 eps
of that pivot and both stay; otherwise both are in the remainder. Pairs of a pivot and a document that it takes are compared exactly. Regions
whose documents are in one component then are dropped, for no further link can change a component; in the others the documents outside the largest
component are compared with all others, and regions too large for that are joined recursively by cells and remainders.

A comparison first bounds the symmetric difference from below by the odd sketches of the two sets (the parity of the number of elements in
each of 0.75n to 1.5n buckets, and of 16n to 32n for the regions that are left), which settles nearly all pairs that are not linked. Sketches travel with the documents of a region, so
a task compares them in memory and its rows are documents with their pivots, at most a few for each document and
region. Only pairs that the bound lets through are compared exactly, from the texts. Windows may use the bound, since they may hold too much; links never do.

Regions that hold more than `crowd` documents never meet in one task: their members travel as rows, and are compared with a few pivots by joins.

Defined results: null or empty texts and texts without words have n_shingles 0, link with nothing and are their own
component; equal sets share a component; rows that repeat a doc_id are one document (the component of the id).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from retro.llm import vector_text as vt
from retro.llm.runtime import checkpointed, components, id_and_text, lean, sorted_groups, tidy

_GOLDEN = np.uint64(0x9E3779B97F4A7C15)


#: Bits of a sketch for four elements: of those that travel with first regions, and of those that settle regions that are left.
COARSE, FINE = 3, 64
#: Count of a shingle that a batch shows to be crowded.
MANY = (1 << 16) - 1


def sketch_words(sizes: np.ndarray, density: int = COARSE) -> np.ndarray:
    """64-bit words of the sketches of sets of these sizes: a power of two, one word at least."""
    return 1 << np.frexp(-(-density * sizes // 256) - 1.0)[1].astype(np.int64).clip(0)


class Sketches:
    """Sizes and odd sketches of sets, one after the other in flat arrays."""

    def __init__(self, density: int = COARSE):
        self.density = density
        self._parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []

    def add(self, identity: np.ndarray, size: np.ndarray, words: np.ndarray) -> None:
        self._parts.append((identity, size, words))

    def finished(self, distinct: bool = True) -> np.ndarray:
        """The place of each added set, equal identities at one place."""
        self.identity, self.size, self._flat = (np.concatenate([p[k] for p in self._parts]) for k in range(3))
        self._parts = []
        self.size = self.size.astype(np.int64)
        self._words = sketch_words(self.size, self.density)
        self._at = np.cumsum(self._words) - self._words
        if not distinct:
            return np.arange(len(self.identity))
        self.identity, first, back = np.unique(self.identity, return_index=True, return_inverse=True)
        self.size, self._words, self._at = self.size[first], self._words[first], self._at[first]
        return back

    def least(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """At most the symmetric differences of sets a[k] and b[k]. The longer sketch is folded to the shorter one's buckets."""
        out = np.zeros(len(a), dtype=np.int64)
        kind = self._words[a] * (1 << 32) + self._words[b]
        for k in np.unique(kind).tolist():
            x, y = divmod(k, 1 << 32)
            where = np.flatnonzero(kind == k)
            step = max(1, (1 << 19) // max(x, y))
            for s in range(0, len(where), step):
                w = where[s : s + step]
                p, q = self._flat[self._at[a[w]][:, None] + np.arange(x)], self._flat[self._at[b[w]][:, None] + np.arange(y)]
                while p.shape[1] > q.shape[1]:
                    p = p[:, : p.shape[1] // 2] ^ p[:, p.shape[1] // 2 :]
                while q.shape[1] > p.shape[1]:
                    q = q[:, : q.shape[1] // 2] ^ q[:, q.shape[1] // 2 :]
                out[w] = np.bitwise_count(p ^ q).sum(axis=1, dtype=np.int64)
        return out


def _rows(region: pa.Array, a: pa.Array, pivot: pa.Array, before: pa.Array) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([region, a, pivot, before], ["region", "a", "pivot", "before"])


def _mixed(before: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Of groups that begin at `first`, those whose members do not all have the same region before: groups of one never."""
    return np.minimum.reduceat(before, first) != np.maximum.reduceat(before, first)


@dataclass(frozen=True)
class JaccardJoin:
    """width: words of a shingle. similar / whole: the threshold as a ratio of integers, so that no rounding decides a link."""

    width: int = 5
    similar: int = 80
    whole: int = 100
    #: Members of one pivot that a task compares exactly.
    members: int = 2048
    #: Shingles that a task counts, about (6 bytes each).
    entries: int = 3_000_000
    #: Shingles that more documents hold, by their count or as a batch's share lets expect, are joined by rows; below MANY.
    crowd: int = 60_000
    #: Sketch comparisons with pivots that a task makes for one region in a round; who is left then is the remainder.
    effort: int = 4_000_000
    #: Pivots that a region takes in a round of joins, and the largest product of its size and its documents outside its
    #: largest component for which a task compares these with all others instead.
    pivots: int = 8
    work: int = 50_000_000
    #: Up to so many wanted documents are broadcast to fetch their texts; more are joined by a shuffle.
    broadcast_rows: int = 500_000

    def linked(self, both, either):
        return self.whole * both >= self.similar * either

    # ---- first level: shingles as pivots ---------------------------------------------------------------------------

    @staticmethod
    def codes(shingles: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
        """The task that counts each shingle, and its 32-bit code there."""
        mixed = vt.mix64(shingles + np.uint64(3))
        return ((mixed >> np.uint64(32)) % np.uint64(parts)).astype(np.int32), mixed.astype(np.uint32)

    def prefix(self, owner: np.ndarray, region: np.ndarray, count: np.ndarray, size: np.ndarray, identity: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(kept, before, order): of the shared shingles of sets, those that name their regions. owner: place of the set in size and identity. order sorts
        the input by set, count and region; kept and before follow it. before is the region before in the set's order, or the set's identity.

        Two shingles of a set whose codes meet arrive as one, so two more than the needed number are kept."""
        order = np.lexsort((region, count, owner))
        owner, region = owner[order], region[order]
        first = np.searchsorted(owner, owner)
        shared = np.searchsorted(owner, owner, side="right") - first
        n = size[owner]
        needed = n - -(-self.similar * n // self.whole) + 1 - (n - shared) + 2
        place = np.arange(len(owner)) - first
        before = np.where(place > 0, np.concatenate(([np.uint64(0)], region[:-1])) if len(region) else region, identity[owner])
        return place < needed, before, order

    def sets(self, texts: pa.Array) -> Iterator[tuple[int, list[np.ndarray]]]:
        for first, _, data, offsets in vt.blocks(texts):
            yield first, vt.shingle_sets(vt.words_of(data, offsets), self.width)

    # ---- the join ------------------------------------------------------------------------------------------------

    @staticmethod
    def sketch(shingles: np.ndarray, density: int = COARSE) -> np.ndarray:
        """Odd sketch, as 64-bit words: bit b is the parity of the number of elements in bucket b."""
        buckets = 64 * (1 << max(0, (-(-density * len(shingles) // 256) - 1).bit_length()))
        odd = np.bincount((vt.mix64(shingles + np.uint64(5)) & np.uint64(buckets - 1)).astype(np.int64), minlength=buckets) & 1
        return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.uint64)

    def bounds(self, sizes: np.ndarray, least: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether two sets may link and may be within twice a link's distance: from the sum of their sizes and a lower bound of
        their symmetric difference."""
        reach = 2 * (1 - self.similar / self.whole) + 1e-9
        return least * (self.whole + self.similar) <= sizes * (self.whole - self.similar), 2 * least <= reach * (sizes + least)

    @staticmethod
    def identity(shingles: np.ndarray) -> np.uint64:
        return np.add.reduce(vt.mix64(shingles ^ _GOLDEN))

    def sizes(self, docs: DataFrame) -> DataFrame:
        """(doc_id, n_shingles, f1, f2, sketch): f1, f2 identify the set."""

        def run(batches):
            for batch in batches:
                rows = batch.num_rows
                n, f1, f2, sketch = *(np.zeros(rows, dtype=np.int64) for _ in range(3)), [None] * rows
                for first, found in self.sets(batch.column("text")):
                    for i, x in enumerate(found, first):
                        if len(x):
                            n[i], sketch[i] = len(x), self.sketch(x).tobytes()
                            f1[i] = self.identity(x).view(np.int64)
                            f2[i] = np.bitwise_xor.reduce(vt.mix64(x + np.uint64(97))).view(np.int64)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n), pa.array(f1), pa.array(f2), pa.array(sketch, pa.binary())], ["doc_id", "n_shingles", "f1", "f2", "sketch"])

        return id_and_text(docs).mapInArrow(lean(run), "doc_id long, n_shingles long, f1 long, f2 long, sketch binary")

    def shared(self, docs: DataFrame, documents: int, parts: int) -> DataFrame:
        """Packed (identity of a set, code of a shingle, its count) of every shingle that two different sets hold, by the sets' task.

        A shingle that a batch shows to be crowded sends a mark to its counting task; its entries go to the sets with the count MANY, and so do all entries that meet the mark.
        """
        share = min(self.crowd, MANY - 1) / max(1, documents)
        names = ["part", "source", "key", "which", "identity", "count"]
        types = [pa.int32(), pa.int32(), *[pa.binary()] * 4]

        def back(source: int, own: np.ndarray, key: np.ndarray, count: np.ndarray):
            """Rows for the sets' tasks: entries of one counting task."""
            to = (own % np.uint64(parts)).astype(np.int64)
            order = np.lexsort((own, to))
            own, key, count, to = own[order], key[order], count[order], to[order]
            cuts = np.searchsorted(to, np.arange(parts + 1))
            return [(p, source, key[a:b].tobytes(), None, own[a:b].tobytes(), count[a:b].astype(np.uint16).tobytes()) for p, (a, b) in enumerate(zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)) if b > a]

        def rows(out):
            return pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(types)], names)

        def emit(batches):
            for batch in (b.slice(k, 4096) for b in batches for k in range(0, b.num_rows, 4096)):
                found = {}
                for _, block in self.sets(batch.column("text")):
                    for x in block:
                        if len(x):
                            found.setdefault(self.identity(x), x)
                if not found:
                    continue
                identity, size = np.array(list(found), dtype=np.uint64), np.array([len(x) for x in found.values()])
                shingles = np.concatenate(list(found.values()))
                found.clear()
                to, key = self.codes(shingles, parts)
                which = np.repeat(np.arange(len(size), dtype=np.uint16), size)
                out = []
                if (most := max(2, batch.num_rows * share)) < len(size):
                    code, back_at, n = np.unique(to.astype(np.uint64) << np.uint64(32) | key, return_inverse=True, return_counts=True)
                    many = (n > most)[back_at]
                    for source in np.unique(to[many]).tolist():
                        at = np.flatnonzero(many & (to == source))
                        out += back(source, identity[which[at]], key[at], np.full(len(at), MANY))
                    marks = code[n > most]
                    to, key, which = to[~many], key[~many], which[~many]
                    to, key = np.concatenate([to, (marks >> np.uint64(32)).astype(np.int32)]), np.concatenate([key, marks.astype(np.uint32)])
                    which = np.concatenate([which, np.full(len(marks), MANY, np.uint16)])
                order = np.argsort(to.astype(np.uint16) if parts < 1 << 16 else to, kind="stable")
                key, which, to = key[order], which[order], to[order]
                cuts = np.searchsorted(to, np.arange(parts + 1)).tolist()
                packed = identity.tobytes()
                out += [(p, -1, key[a:b].tobytes(), which[a:b].tobytes(), packed, None) for p, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if b > a]
                yield rows(out)

        def count(batches):
            entries, identities, known, part = [], [], 0, 0
            for batch in batches:
                done = pa.compute.greater_equal(batch.column("source"), 0)
                if done.true_count:
                    yield batch.filter(done)
                for r in batch.filter(pc.invert(done)).to_pylist():
                    if entries and part != r["part"]:
                        yield from counted(entries, identities, part)
                        entries, identities, known = [], [], 0
                    part, which = r["part"], np.frombuffer(r["which"], np.uint16).astype(np.int64)
                    entries.append(np.frombuffer(r["key"], np.uint32).astype(np.uint64) << np.uint64(32) | np.where(which == MANY, 0, which + known + 1).astype(np.uint64))
                    identities.append(np.frombuffer(r["identity"], np.uint64))
                    known += len(identities[-1])
            if entries:
                yield from counted(entries, identities, part)

        def counted(entries, identities, part):
            identity, own_at = np.unique(np.concatenate(identities), return_inverse=True)
            identities.clear()
            rank = np.concatenate(([0], own_at + 1)).astype(np.uint64)  # 0 stays the mark
            held = np.concatenate(entries)
            entries.clear()
            held = held & np.uint64(0xFFFFFFFF << 32) | rank[held & np.uint64(0xFFFFFFFF)]
            held.sort()
            held = held[np.concatenate(([True], held[1:] != held[:-1]))]
            key, own = (held >> np.uint64(32)).astype(np.uint32), (held & np.uint64(0xFFFFFFFF)).astype(np.int64) - 1
            first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
            n = np.diff(np.append(first, len(key)))
            size = np.repeat(np.where(own[first] < 0, MANY, np.minimum(n, MANY - 1)), n)
            keep = (own >= 0) & (size > 1)
            if keep.any():
                yield rows(back(part, identity[own[keep]], key[keep], size[keep]))

        schema = "part int, source int, key binary, which binary, identity binary, count binary"
        sent = id_and_text(docs).mapInArrow(lean(emit), schema)
        return sent.repartition(parts, "part").sortWithinPartitions("part").mapInArrow(lean(count), schema)

    def regions(self, docs: DataFrame, classes: DataFrame, parts: int) -> DataFrame:
        """The first level and its document pivots: (region, a, pivot, before) with sets by their identity. A row with a pivot is a pair that may link;
        one without is a member that its region keeps, with the region before in its order (null in crowded regions)."""
        names = ["part", "key", "before", "which", "identity", "size", "sketch", "region", "a"]

        def pack(batches):
            for batch in batches:
                own, size = batch.column("f1").to_numpy().view(np.uint64), batch.column("n_shingles").to_numpy()
                sketch = batch.column("sketch").to_pylist()
                to = (own % np.uint64(parts)).astype(np.int64)
                out = []
                for p in np.unique(to).tolist():
                    at = np.flatnonzero(to == p)
                    out.append((p, -2, b"".join(sketch[k] for k in at.tolist()), None, own[at].tobytes(), size[at].astype(np.int32).tobytes()))
                types = [pa.int32(), pa.int32(), *[pa.binary()] * 4]
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(types)], ["part", "source", "key", "which", "identity", "count"])

        def name(batches):
            held, entries, part = [], [], None
            for batch in batches:
                for r in batch.to_pylist():
                    if part is not None and r["part"] != part:
                        yield from named(held, entries)
                        held, entries = [], []
                    part = r["part"]
                    own = np.frombuffer(r["identity"], np.uint64)
                    if r["source"] == -2:
                        held.append((own, np.frombuffer(r["count"], np.int32), np.frombuffer(r["key"], np.uint64)))
                    else:
                        region = np.frombuffer(r["key"], np.uint32) | np.uint64(r["source"]) << np.uint64(32)
                        entries.append((own, region, np.frombuffer(r["count"], np.uint16)))
            if held and entries:
                yield from named(held, entries)

        def named(held, entries):
            if not held or not entries:
                return
            identity, size, words = (np.concatenate([h[k] for h in held]) for k in range(3))
            own, region, count = (np.concatenate([e[k] for e in entries]) for k in range(3))
            word = np.concatenate(([0], np.cumsum(sketch_words(size.astype(np.int64)))))
            by = np.argsort(identity)
            which = by[np.searchsorted(identity[by], own)]
            keep, before, order = self.prefix(which, region, count, size.astype(np.int64), identity)
            region, which, count, before = region[order][keep], which[order][keep], count[order][keep], before[keep]
            many = count > min(self.crowd, MANY - 1)
            if many.any():
                packed = [pa.nulls(int(many.sum()), pa.binary())] * 6
                yield pa.RecordBatch.from_arrays([pa.array((identity[which[many]] % np.uint64(parts)).astype(np.int32)), *packed, pa.array(region[many].view(np.int64)), pa.array(identity[which[many]].view(np.int64))], names)
            region, which, before = region[~many], which[~many], before[~many]
            to = (vt.mix64(region) % np.uint64(parts)).astype(np.int64)
            order = np.argsort(to, kind="stable")
            region, which, before, to = region[order], which[order], before[order], to[order]
            cuts, out = np.searchsorted(to, np.arange(parts + 1)).tolist(), []
            for p, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
                if b > a:
                    mine, local = np.unique(which[a:b], return_inverse=True)
                    sent = np.concatenate([words[word[k] : word[k + 1]] for k in mine.tolist()])
                    out.append((p, region[a:b].tobytes(), before[a:b].tobytes(), local.astype(np.int32).tobytes(), identity[mine].tobytes(), size[mine].astype(np.int32).tobytes(), sent.tobytes(), None, None))
            types = [pa.int32(), *[pa.binary()] * 6, pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(types)], names)

        def gather(batches):
            parts, known, held = [], 0, Sketches()
            for batch in batches:
                plain = batch.column("key").is_null()
                if plain.true_count:
                    rest = batch.filter(plain)
                    none = pa.nulls(rest.num_rows, pa.int64())
                    yield _rows(rest.column("region"), rest.column("a"), none, none)
                for r in batch.filter(pc.invert(plain)).select(names[1:7]).to_pylist():
                    identity = np.frombuffer(r["identity"], np.uint64)
                    parts.append([np.frombuffer(r["key"], np.uint64), np.frombuffer(r["before"], np.uint64), np.frombuffer(r["which"], np.int32) + known])
                    known += len(identity)
                    held.add(identity, np.frombuffer(r["size"], np.int32), np.frombuffer(r["sketch"], np.uint64))
            if parts:
                key, before, own = (np.concatenate([p.pop(0) for p in parts]) for _ in range(3))
                own = held.finished()[own]
                order = np.argsort(key, kind="stable")
                yield from self.first_round(key[order], before[order], own[order], held)

        info = classes.select("f1", "n_shingles", "sketch").mapInArrow(lean(pack), "part int, source int, key binary, which binary, identity binary, count binary")
        documents = classes.count()
        entries = self.shared(docs, documents, parts).unionByName(info).repartition(parts, F.col("part") + 0).sortWithinPartitions("part")
        sent = entries.mapInArrow(lean(name), "part int, key binary, before binary, which binary, identity binary, size binary, sketch binary, region long, a long")
        return sent.repartition(parts, "part").mapInArrow(lean(gather), "region long, a long, pivot long, before long")

    def first_round(self, key: np.ndarray, before: np.ndarray, own: np.ndarray, held: Sketches) -> Iterator[pa.RecordBatch]:
        """Cuts regions by size, drops those whose members meet elsewhere, lets pivots take the members of the rest. key is sorted."""
        size = held.size[own]
        order = np.lexsort((size, key))
        key, before, own, size = key[order], before[order], own[order], size[order]
        if len(key) < 2:
            return
        cut = np.concatenate(([True], (key[1:] != key[:-1]) | (size[:-1] * self.whole < size[1:] * self.similar)))
        keep = np.repeat(_mixed(before, np.flatnonzero(cut)), np.diff(np.append(np.flatnonzero(cut), len(key))))
        region = np.cumsum(cut)[keep]
        key, before, own = vt.mix64(key[keep] + _GOLDEN * region.astype(np.uint64)), before[keep], own[keep]
        order = np.lexsort((held.identity[own], region))  # pivots are the same in all regions that a group of documents shares
        key, before, own, region = key[order], before[order], own[order], region[order]
        a, pivot, stay = self.taken(region, own, held)
        pairs = np.unique(np.stack([a, pivot]), axis=1)
        none = pa.nulls(pairs.shape[1], pa.int64())
        yield _rows(none, *(pa.array(held.identity[x].view(np.int64)) for x in pairs), none)
        key, before, own, region = key[stay], before[stay], own[stay], region[stay]
        if len(key):
            first = np.flatnonzero(np.concatenate(([True], region[1:] != region[:-1])))
            keep = np.repeat(_mixed(before, first), np.diff(np.append(first, len(key))))
            yield _rows(pa.array(key[keep].view(np.int64)), pa.array(held.identity[own[keep]].view(np.int64)), pa.nulls(int(keep.sum()), pa.int64()), pa.array(before[keep].view(np.int64)))

    def taken(self, region: np.ndarray, own: np.ndarray, held: Sketches) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(members, pivots, stay) of regions (sorted): each taken document with its pivot, and whether each row stays: who may link with a pivot or, if any member
        may, be in its window; pivots that may link with a document that another one has taken; and whom no pivot has taken when a region's effort is
        spent. All regions take their next pivot at once."""
        first = np.flatnonzero(np.concatenate(([True], region[1:] != region[:-1]))) if len(region) else np.zeros(0, np.int64)
        n = np.diff(np.append(first, len(region)))
        free, member, stay = np.ones(len(region), dtype=bool), np.ones(len(region), dtype=bool), np.zeros(len(region), dtype=bool)
        members, pivots, turn = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0
        while len(first):
            starts = np.concatenate(([0], np.cumsum(n)[:-1]))
            rows = np.repeat(first - starts, n) + np.arange(int(n.sum()))
            pivot = np.minimum.reduceat(np.where(free[rows], rows, len(region)), starts)
            live = (pivot < len(region)) & (np.add.reduceat(member[rows].astype(np.int64), starts) > 1)
            spent = live & ((turn + 1) * n > self.effort) & (turn > 0)
            left = rows[np.repeat(spent, n)]
            stay[left[free[left]]] = True
            live &= ~spent
            rows, first, n, pivot = rows[np.repeat(live, n)], first[live], n[live], pivot[live]
            if not len(first):
                break
            free[pivot] = member[pivot] = False
            by = np.repeat(pivot, n)
            some = member[rows]
            rows, by = rows[some], by[some]
            sizes = held.size[own[rows]] + held.size[own[by]]
            close, window = self.bounds(sizes, held.least(own[rows], own[by]))
            new = close & free[rows]
            free[rows[close]] = False
            found = np.zeros(len(region), dtype=bool)
            found[by[close]] = True
            stay[rows[(close | window) & found[by]]] = True
            stay[by[close & ~new]] = True
            members.append(own[rows[new]])
            pivots.append(own[by[new]])
            turn += 1
        return np.concatenate(members), np.concatenate(pivots), stay

    # ---- later rounds ----------------------------------------------------------------------------------------------

    def screened(self, pairs: DataFrame, classes: DataFrame) -> DataFrame:
        """(region, doc, pivot, role): members of regions with their pivots, compared by sketches; role null: neither close nor in the window."""
        own, other = (classes.select(F.col("doc").alias(k), F.col("n_shingles").alias(f"n_{k}"), F.col("sketch").alias(f"sketch_{k}")) for k in ("doc", "pivot"))
        rows = pairs.join(own.hint("merge"), "doc").join(other.hint("merge"), "pivot")

        def run(batches):
            for batch in batches:
                held = Sketches()
                for k in ("doc", "pivot"):
                    held.add(np.zeros(batch.num_rows, np.uint64), batch.column(f"n_{k}").to_numpy(), np.frombuffer(b"".join(batch.column(f"sketch_{k}").to_pylist()), np.uint64))
                held.finished(distinct=False)
                at = np.arange(batch.num_rows)
                close, window = self.bounds(batch.column("n_doc").to_numpy() + batch.column("n_pivot").to_numpy(), held.least(at, at + batch.num_rows))
                yield pa.RecordBatch.from_arrays([batch.column("region"), batch.column("doc"), batch.column("pivot"), pa.array(np.where(close, 0, 1).astype(np.int32), mask=~(close | window))], ["region", "doc", "pivot", "role"])

        return rows.select("region", "doc", "pivot", "n_doc", "n_pivot", "sketch_doc", "sketch_pivot").mapInArrow(run, "region long, doc long, pivot long, role int")

    def fine(self, docs: DataFrame, wanted: DataFrame, classes: DataFrame) -> DataFrame:
        """(doc, n_shingles, sketch) of the wanted documents, with fine sketches from their texts."""

        def run(batches):
            for batch in batches:
                for first, found in self.sets(batch.column("text")):
                    own = batch.column("doc_id").slice(first, len(found))
                    kept = pa.array([bool(len(x)) for x in found])
                    some = [x for x in found if len(x)]
                    yield pa.RecordBatch.from_arrays([own.filter(kept), pa.array([self.identity(x) for x in some], pa.uint64()).view(pa.int64()), pa.array([self.sketch(x, FINE).tobytes() for x in some], pa.binary())], ["doc", "f1", "sketch"])

        wanted = checkpointed(wanted)
        side = F.broadcast(wanted) if wanted.count() <= self.broadcast_rows else wanted.hint("merge")
        rows = id_and_text(docs).join(side, F.col("doc_id") == F.col("doc"), "left_semi").mapInArrow(lean(run), "doc long, f1 long, sketch binary")
        return rows.join(classes.select("doc", "f1", "n_shingles").hint("merge"), ["doc", "f1"]).groupBy("doc").agg(F.first("n_shingles").alias("n_shingles"), F.first("sketch").alias("sketch"))

    def compared(self, cells: DataFrame, sketches: DataFrame) -> DataFrame:
        """Pairs (doc, pivot) of one region that may link and lie in two components, the pivot outside the region's largest one. Two documents that
        have the same region before meet there as well and are not compared here."""
        rows = cells.join(sketches.hint("merge"), "doc").select("region", "doc", "comp", "before", "n_shingles", "sketch")

        def run(batches):
            for group in sorted_groups(batches, ["region"]):
                region, doc, comp, n = (group.column(k).to_numpy() for k in ("region", "doc", "comp", "n_shingles"))
                known = group.column("before").is_valid().to_numpy()
                before = group.column("before").fill_null(0).to_numpy()
                held = Sketches(FINE)
                held.add(np.zeros(len(n), np.uint64), n, np.frombuffer(b"".join(group.column("sketch").to_pylist()), np.uint64))
                held.finished(distinct=False)
                ends = np.append(np.flatnonzero(region[1:] != region[:-1]) + 1, len(region))
                found, start = [], 0
                for end in ends.tolist():
                    kinds, back, many = np.unique(comp[start:end], return_inverse=True, return_counts=True)
                    rank = np.where(np.arange(len(kinds)) == np.argmax(many), len(kinds), np.arange(len(kinds)))[back]
                    for k in np.flatnonzero(rank < len(kinds)).tolist():
                        other = start + np.flatnonzero((rank > rank[k]) & (~known[start:end] | (before[start:end] != before[start + k])))
                        close, _ = self.bounds(n[other] + n[start + k], held.least(other, np.full(len(other), start + k)))
                        found.append(np.stack([doc[other[close]], np.full(int(close.sum()), doc[start + k])]))
                    start = end
                a, b = np.unique(np.concatenate(found, axis=1), axis=1) if found else np.zeros((2, 0), np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["doc", "pivot"])

        return rows.repartition("region").sortWithinPartitions("region").mapInArrow(lean(run), "doc long, pivot long")

    def linked_pairs(self, docs: DataFrame, pairs: DataFrame, bound: int) -> DataFrame:
        """Those of the distinct pairs (doc, pivot), at most `bound`, whose sets link, compared exactly."""
        salts = pairs.groupBy("pivot").agg(F.ceil(F.count("*") / self.members).cast("int").alias("salts"))
        wanted = (
            pairs.join(salts.hint("merge"), "pivot")
            .select("doc", "pivot", F.pmod(F.xxhash64("doc"), F.col("salts")).cast("int").alias("salt"), F.lit(1).alias("role"))
            .unionByName(salts.select(F.col("pivot").alias("doc"), "pivot", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.lit(0).alias("role")))
        )
        few = bound <= self.broadcast_rows
        rows = id_and_text(docs).join(F.broadcast(wanted) if few else wanted.hint("merge"), F.col("doc_id") == F.col("doc")).select("pivot", "salt", "role", "doc", "text")
        rows = rows.repartition("pivot", "salt").sortWithinPartitions("pivot", "salt", "role", "doc")

        def run(batches):
            at, base = None, None
            for batch in batches:
                pivot, salt, role, doc = (batch.column(k).to_numpy() for k in ("pivot", "salt", "role", "doc"))
                out = []
                for first, found in self.sets(batch.column("text")):
                    for i, x in enumerate(found, first):
                        if role[i] == 0:
                            at, base = (pivot[i], salt[i]), x
                        elif at == (pivot[i], salt[i]):
                            both = len(np.intersect1d(base, x, assume_unique=True))
                            if self.linked(both, len(base) + len(x) - both):
                                out.append(i)
                yield batch.select(["doc", "pivot"]).take(pa.array(out, pa.int64()))

        return rows.mapInArrow(run, "doc long, pivot long")

    def mixed(self, cells: DataFrame, comps: DataFrame) -> DataFrame:
        """(region, doc, before, comp) of the regions that hold more than one component."""
        cells = cells.join(comps.hint("merge"), F.col("doc") == F.col("node"), "left").select("region", "doc", "before", F.coalesce("component", "doc").alias("comp"))
        two = cells.groupBy("region").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("region")
        return checkpointed(checkpointed(cells).join(two.hint("merge"), "region", "left_semi"))

    def settled(self, docs: DataFrame, close: DataFrame, links: DataFrame | None = None, comps: DataFrame | None = None, tried: DataFrame | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
        """All links found so far, (node, component) of them and the pairs compared so far, from pairs that may link. Each document is compared with
        its least partner first; of the other pairs only those are compared exactly that still lie in two components."""
        close = close.select(F.greatest("doc", "pivot").alias("doc"), F.least("doc", "pivot").alias("pivot")).distinct()
        if tried is not None:
            close = close.join(tried.hint("merge"), ["doc", "pivot"], "left_anti")
        close = checkpointed(close)
        n = close.count()
        if tried is not None and not n:
            return links, comps, tried
        first = close.groupBy("doc").agg(F.min("pivot").alias("pivot"))
        links, comps = self._joined(docs, first, n, links)
        label = lambda k: comps.select(F.col("node").alias(k), F.col("component").alias(f"comp_{k}")).hint("merge")
        rest = close.join(label("doc"), "doc", "left").join(label("pivot"), "pivot", "left")
        rest = rest.where(F.coalesce("comp_doc", "doc") != F.coalesce("comp_pivot", "pivot")).select("doc", "pivot")
        rest = checkpointed(rest.join(first.hint("merge"), ["doc", "pivot"], "left_anti"))
        n = rest.count()
        tidy(docs.sparkSession)
        tried = first.unionByName(rest) if tried is None else tried.unionByName(first).unionByName(rest)
        return *(self._joined(docs, rest, n, links) if n else (links, comps)), checkpointed(tried)

    def _joined(self, docs: DataFrame, pairs: DataFrame, bound: int, links: DataFrame | None) -> tuple[DataFrame, DataFrame]:
        found = self.linked_pairs(docs, pairs, bound)
        links = checkpointed(found if links is None else links.unionByName(found))
        return links, checkpointed(components(links.select(F.col("doc").alias("a"), F.col("pivot").alias("b"))))

    def cells(self, rows: DataFrame, links: DataFrame) -> DataFrame:
        """(region, doc, before) of the cells of pivots that some document links with, and of the remainders, from (region, doc, pivot, role)."""
        both = links.select("doc", "pivot").unionByName(links.select(F.col("pivot").alias("doc"), F.col("doc").alias("pivot"))).withColumn("linked", F.lit(1))
        known = rows.join(both.hint("merge"), ["doc", "pivot"], "left").select("region", "doc", "pivot", "role", F.coalesce("linked", F.lit(0)).alias("linked"))
        alive = known.where("role < 2").groupBy("region", "pivot").agg(F.max("linked").alias("alive"), F.count("*").alias("n")).where("alive = 1 and n > 1").select("region", "pivot")
        cell = known.where("role < 2").join(alive.hint("merge"), ["region", "pivot"]).select(F.xxhash64("region", "pivot").alias("region"), "doc")
        left = known.where("role <> 1").groupBy("region", "doc").agg(F.max("linked").alias("linked")).where("linked = 0")
        return cell.unionByName(left.select(F.xxhash64("region", F.lit("rest")).alias("region"), "doc")).withColumn("before", F.lit(None).cast("long"))

    def join(self, docs: DataFrame) -> DataFrame:
        """(doc_id, n_shingles, component_id) for every row of docs."""
        spark = docs.sparkSession
        size = checkpointed(self.sizes(docs))
        classes = checkpointed(size.where("n_shingles > 0").groupBy("f1", "f2", "n_shingles").agg(F.min("doc_id").alias("doc"), F.first("sketch").alias("sketch")))
        size = size.drop("sketch")
        shingles = classes.agg(F.sum("n_shingles")).first()[0] or 0
        found = self.regions(docs, classes, max(8, -(-shingles // self.entries)))
        of = lambda k, name: classes.select(F.col("f1").alias(k), F.col("doc").alias(name)).hint("merge")
        found = checkpointed(checkpointed(found).join(of("a", "doc"), "a").join(of("pivot", "taker"), "pivot", "left").select("region", "doc", F.col("taker").alias("pivot"), "before"))
        links, comps, tried = self.settled(docs, found.where("pivot is not null").select("doc", "pivot"))
        cells = self.mixed(found.where("pivot is null").select("region", "doc", "before"), comps)
        while not cells.isEmpty():
            tidy(spark)
            part = cells.groupBy("region", "comp").agg(F.count("*").alias("m")).groupBy("region").agg(F.max("m").alias("m"), F.sum("m").alias("size"))
            cells = checkpointed(cells.join(part.select("region", "size", ((F.col("size") - F.col("m")) * F.col("size")).alias("work")).hint("merge"), "region"))
            small = (F.col("work") <= self.work) & (F.col("size") <= self.crowd)
            sketches = checkpointed(self.fine(docs, cells.where(small).select("doc").distinct(), classes))
            close = self.compared(cells.where(small), sketches)
            cells = cells.where(~small)
            last = cells.isEmpty()
            if not last:
                rank = F.row_number().over(Window.partitionBy("region").orderBy("doc"))
                chosen = checkpointed(cells.select("region", F.col("doc").alias("pivot"), rank.alias("k")).where(F.col("k") <= self.pivots).drop("k"))
                others = checkpointed(cells.select("region", "doc").join(chosen.withColumnRenamed("pivot", "doc").hint("merge"), ["region", "doc"], "left_anti"))
                # pivots are compared among themselves as well, each with those before it
                both = others.unionByName(chosen.select("region", F.col("pivot").alias("doc")))
                met = self.screened(both.join(chosen.hint("merge"), "region").where("doc <> pivot"), classes).where("role is not null")
                met = checkpointed(met)
                rows = met.join(chosen.select("region", F.col("pivot").alias("doc")).hint("merge"), ["region", "doc"], "left_anti")
                rows = checkpointed(rows.select("region", "doc", "pivot", "role").unionByName(others.select("region", "doc", F.lit(None).cast("long").alias("pivot"), F.lit(2).alias("role"))))
                close = close.unionByName(met.where("role = 0").select("doc", "pivot"))
            links, comps, tried = self.settled(docs, close, links, comps, tried)
            if last:
                break
            cells = self.mixed(self.cells(rows, links), comps)
        classed = classes.join(comps.hint("merge"), F.col("doc") == F.col("node"), "left").select("f1", "f2", "n_shingles", F.coalesce("component", "doc").alias("component_id"))
        out = size.join(classed.hint("merge"), ["f1", "f2", "n_shingles"], "left")
        return out.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
