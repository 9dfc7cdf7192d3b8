"""Packing token sequences: best fit decreasing, then swap-based local search.

Documents longer than a sequence are cut into full pieces, the first one shorter where
needed.  Pieces are dealt over shards by a hash, so many shards that each holds some
twenty million tokens at any input size, and each shard is packed by itself: best fit
decreasing, then moves, one-for-one and two-for-one exchanges between underfull bins.  Each
step raises the sum of squared fills, so the emptiest bins drain until they vanish.  The
search ends where no step is left or the fewest bins that can hold all are reached.  A
shard leaves some bins underfull; the poorest of up to FAN shards are then packed together
by the same search, and so on until all shards have met.

Defined results: null texts are empty and hold the separator only; repeated rows, and rows
without an id, are packed separately; an empty table gives no rows; ties go by row order
inside a shard; other columns are not read, whatever their names; a text is encoded as a
whole, and a long one's pieces are dealt over all shards.
"""

from __future__ import annotations

import math
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.llm.bpe_dp import LibraryEncoder, texts_of
from gridlake.llm.common import Scratch

CAPACITY = 2048
SEPARATOR = (0).to_bytes(4, "little")
#: Characters and documents in a shard, about.
SHARD_CHARS, SHARD_DOCS = 60_000_000, 20_000
#: Shards whose poorest bins meet, and how many of them each sends.
FAN, POOREST = 64, 64

PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long, home long"
PACKED = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
OPEN = f"{PACKED}, poor boolean, home long"


def cuts(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """Start and length of the pieces of a document of ``n`` tokens."""
    first = (n - 1) % capacity + 1
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


def piece_rows(docs: DataFrame, tokenizer: str, shards: int) -> DataFrame:
    """The pieces of all documents, each with its shard and no place yet."""

    def run(batches):
        enc = LibraryEncoder.load(tokenizer)
        for batch in batches:
            ids, rows = batch.column(0).to_pylist(), []
            for k, (doc, text) in enumerate(zip(ids, texts_of(batch.column(1)), strict=True)):
                packed = enc.encode(text) + SEPARATOR
                for piece, (start, length) in enumerate(cuts(len(packed) // 4)):
                    crc = zlib.crc32(packed[4 * start : 4 * (start + length)])
                    rows.append((doc, piece, start, length, crc, -1, 0, zlib.crc32(b"%d %d %d" % (doc or 0, piece, k)) % shards))
            cols = list(zip(*rows, strict=True)) or [[]] * 8
            types = (pa.int64(), pa.int32(), *[pa.int64()] * 6)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], [x.split()[0] for x in PIECE.split(", ")])

    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return plain.mapInArrow(run, PIECE)


class Bins:
    """Bins of items, indexed by what is left in them."""

    def __init__(self, sizes: list[int], capacity: int):
        self.sizes, self.capacity = sizes, capacity
        self.items: list[list[int]] = []
        self.left: list[int] = []
        self.by_left: list[set[int]] = [set() for _ in range(capacity + 1)]
        self.mask = 0

    def _index(self, b: int) -> None:
        r = self.left[b]
        self.by_left[r].add(b)
        self.mask |= 1 << r

    def _unindex(self, b: int) -> None:
        r = self.left[b]
        self.by_left[r].discard(b)
        if not self.by_left[r]:
            self.mask &= ~(1 << r)

    def tightest(self, size: int) -> int | None:
        """The bin with the least room that still holds ``size``."""
        m = self.mask >> size
        return next(iter(self.by_left[size + (m & -m).bit_length() - 1])) if m else None

    def change(self, b: int, out: list[int], into: list[int]) -> None:
        self._unindex(b)
        for i in out:
            self.items[b].remove(i)
        self.items[b] += into
        self.left[b] += sum(self.sizes[i] for i in out) - sum(self.sizes[i] for i in into)
        if self.items[b]:
            self._index(b)

    def best_fit(self, i: int) -> None:
        b = self.tightest(self.sizes[i])
        if b is None:
            b = len(self.items)
            self.items.append([])
            self.left.append(self.capacity)
            self._index(b)
        self.change(b, [], [i])

    def used(self) -> int:
        return sum(map(bool, self.items))


def improve(bins: Bins) -> None:
    """Local search to its end; every step raises the sum of squared fills."""
    sizes = bins.sizes
    least = math.ceil(sum(sizes) / bins.capacity)
    changed = True
    while changed:
        changed = False
        poor = sorted((b for b, own in enumerate(bins.items) if own and bins.left[b]), key=lambda b: -bins.left[b])
        if bins.used() <= least or len(poor) < 2:
            return
        of_size: dict[int, set[int]] = defaultdict(set)  # of items in underfull bins
        place = {}
        for b in poor:
            for i in bins.items[b]:
                of_size[sizes[i]].add(i)
                place[i] = b

        def swap(a: int, out: list[int], b: int, back: list[int]) -> None:
            bins.change(b, back, [])
            bins.change(a, out, back)
            bins.change(b, [], out)
            for i in out:
                place[i] = b
            for i in back:
                place[i] = a

        def partner(a: int, size: int) -> int | None:
            """An item, smaller than ``size``, in a bin at least as full that has the room."""
            widest = bins.mask.bit_length() - 1
            for s in range(size - 1, max(0, size - 1 - widest), -1):
                for j in of_size.get(s, ()):
                    b = place[j]
                    if b != a and bins.left[b] <= bins.left[a] and bins.left[b] >= size - s:
                        return j
            return None

        def two_for_one(a: int) -> tuple[list[int], int, list[int]] | None:
            """A pair of the bin's items, another bin and its item to exchange; equal sums are tried once."""
            own: dict[int, list[int]] = defaultdict(list)
            for i in bins.items[a]:
                own[sizes[i]].append(i)
            sums = {s + t: (own[s][0], own[t][s == t]) for s in own for t in own if s < t or (s == t and len(own[s]) > 1)}
            for total in sorted(sums):
                if (j := partner(a, total)) is not None:
                    return list(sums[total]), place[j], [j]
            return None

        for a in poor:
            for i in sorted(bins.items[a], key=sizes.__getitem__, reverse=True):
                if place.get(i) != a:
                    continue
                bins._unindex(a)
                b = bins.tightest(sizes[i])
                bins._index(a)
                if b is not None and bins.left[b] <= bins.left[a]:
                    bins.change(a, [i], [])
                    bins.change(b, [], [i])
                    place[i] = b
                    changed = True
                    continue
                j = partner(a, sizes[i])
                if j is not None:
                    swap(a, [i], place[j], [j])
                    changed = True
            while (pair := two_for_one(a)) is not None:
                swap(a, *pair)
                changed = True


def pack(sizes: list[int], capacity: int = CAPACITY) -> list[list[int]]:
    """Bins of item numbers."""
    bins = Bins(sizes, capacity)
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        bins.best_fit(i)
    improve(bins)
    return [own for own in bins.items if own]


def placed(table: pa.Table, level: int, home: int) -> pa.Table:
    """Pieces with their sequence and offset, and whether their bin is one of the poorest.

    ``home`` is the shard, or on later levels the pool of shards, that is packed; bins that
    the pieces lie in already are kept there unless fewer are found.
    """
    sizes = table.column("length").to_pylist()
    bins, poor = pack(sizes), np.zeros(len(table), bool)
    sequence, offset = (table.column(c).to_numpy().copy() for c in ("sequence_id", "offset"))
    before = np.unique(sequence).tolist()
    if level and len(bins) >= len(before):
        bins = [np.flatnonzero(sequence == b).tolist() for b in before]
    else:
        for b, own in enumerate(bins):
            at = 0
            for i in own:
                sequence[i], offset[i] = (level << 24 | home) << 32 | b, at
                at += sizes[i]
    filled = sorted((sum(sizes[i] for i in own), b) for b, own in enumerate(bins))
    for full, b in filled[:POOREST]:
        poor[bins[b]] = full < CAPACITY
    names = [x.split()[0] for x in OPEN.split(", ")]
    last = [pa.array(sequence), pa.array(offset), pa.array(poor), pa.array(np.full(len(table), home))]
    return pa.table([*(table.column(c) for c in names[:5]), *last], names=names)


def _placer(level: int):
    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        return placed(table, level, table.column("home")[0].as_py())

    return run


def pack_documents(docs: DataFrame, tokenizer: str, shard_docs: int = SHARD_DOCS, fan: int = FAN) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32, sequence_id, offset`` of every piece."""
    size = docs.agg(F.count("*").alias("rows"), F.sum(F.length(F.col("text").cast("string"))).alias("chars")).first()
    shards = max(1, size.rows // shard_docs, (size.chars or 0) // SHARD_CHARS)
    with Scratch(docs.sparkSession, "pack") as s:
        rows, done = piece_rows(docs, tokenizer, shards), []
        for level in range(64):
            rows = rows.groupBy("home").applyInArrow(_placer(level), OPEN)
            if shards == 1:
                break
            shards = -(-shards // fan)
            rows = s.keep(rows, f"level-{level}")
            done.append(rows.where("NOT poor"))
            rows = rows.where("poor").withColumn("home", F.floor(F.col("home") / fan))
        for part in done:
            rows = rows.unionByName(part)
        return s.keep(rows.select(*[x.split()[0] for x in PACKED.split(", ")]))
