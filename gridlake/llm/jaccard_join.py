"""Exact n-gram Jaccard self-join with set-relation skipping, and its components.

A document's set holds its distinct five-word shingles (64-bit hashes).  The join

1. collapses texts with the same words into classes, and gives classes with equal sets one
   representative,
2. compares representatives that share several min-wise keys with one leader.  The answer,
   the number of common shingles, is kept: it says how far a set is from its leader,
3. finds what may still link different components through an inverted index on prefixes,
   rarest shingles first.  An index list is kept in blocks by set size; inside a block the
   entries are ordered by the shingle's position, so the rest of a block is skipped once
   the position proves that too few shingles remain, and blocks of other components and
   sizes out of range are skipped whole.  A long list is cut into tiles for several tasks,
4. derives the answers of sets that are close to a leader from the leader's: of two
   candidates only their leaders are intersected, and the shingles by which each differs
   from its leader bound what the two can have in common; most pairs need no more,
5. compares what remains.  A link rests on the words: where two texts are found similar by
   hashes, their words and shingles are compared byte by byte first.

Nothing is capped: keys and leaders only decide what steps 3 and 4 need not see.

Defined results: a null or blank text has the empty set, links with nothing and is its own
component; repeated rows are documents of their own; a null id takes no part in the
smallest id of a component unless it stands alone; an empty table gives no rows; other
columns are not read, whatever their names; a text is worked on as a whole, however long.
Two different shingles of one text count as one if their 64-bit hashes are equal.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.llm.common import IdFilter, Scratch, components, doc_chunks, keyed, lean, text_spans
from gridlake.llm.textkernels import Words, plain_texts, shingle_hashes, similar, word_hashes

#: Similarity in hundredths.
THRESHOLD = 80
#: Min-wise keys of a set: the first hash in each part of the hash range.
KEY_BITS = 4
#: Keys that a set and its leader share at least before they are compared.
KEYS_SHARED = 4
#: A shingle in at least so many sets goes to the end of the order.  The least count is
#: doubled until the shingles fit into a Bloom filter of bounded size.
SHARED, SHARED_MOST = 2, 40_000_000
#: Shingles in at least so many sets are ordered by count, the most frequent ones at most.
FREQUENT, FREQUENT_MOST = 64, 1 << 18
#: Bits of a hash that frequencies are counted by.
COUNT_BITS = 40
#: Values that a task sorts at once while counting.
COUNT_CHUNK = 1 << 20
#: Documents whose counts, or index lists, make one group.
BUCKET_DOCS = 2048
#: Entries of an index list that one task goes through at once, about half of it.
TILE_ROWS = 4000
#: Copies of a row that is joined with a hot key.
SALTS = 16
#: Members that one task compares with a leader, about.
SALT_ROWS = 4000


def sets_of(data: np.ndarray, offsets: np.ndarray):
    """The sorted distinct shingle hashes of every text, one after the other."""
    for lo, hi in doc_chunks(offsets):
        words, bounds = word_hashes(data, offsets[lo : hi + 1])
        hashes, cuts = shingle_hashes(words, bounds)
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            own = np.sort(hashes[a:b])
            yield own[np.concatenate(([True], own[1:] != own[:-1]))] if len(own) > 1 else own


def min_wise(own: np.ndarray) -> list[int]:
    """The first hash in each of the equal parts of the range, as signed numbers."""
    parts = own >> np.uint64(64 - KEY_BITS)
    first = np.flatnonzero(np.concatenate(([True], parts[1:] != parts[:-1]))) if len(own) else []
    return own[first].view(np.int64).tolist() if len(own) else []


def pressed(values: np.ndarray) -> bytes:
    """Ascending numbers, as differences by byte planes, compressed."""
    gaps = np.diff(values, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8)
    return zstandard.compress(np.ascontiguousarray(gaps.T).tobytes(), 1)


def unpressed(blob: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.decompress(blob), np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view(np.uint64).ravel())


def by_bucket(high: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Buckets that ascending 32-bit values fall into, and where each begins (len + 1)."""
    own = (high * np.uint64(buckets)) >> np.uint64(32)
    cut = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1], [True])))
    return own[cut[:-1]].astype(np.int64), cut


def summaries(rows: DataFrame, buckets: int) -> DataFrame:
    """For each document its size, digests of its words and its set, and keys; for each task
    its counts of shingles."""

    @lean
    def run(batches):
        shift = np.uint64(64 - COUNT_BITS)
        names = ["rid", "doc_id", "n", "digest", "set", "keys", "bucket", "values", "counts"]
        types = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.list_(pa.int64()), pa.int64(), pa.binary(), pa.binary()]
        seen: set[bytes] = set()
        held, size = [], 0

        def flush():
            values, counts = np.unique(np.concatenate(held), return_counts=True)
            found, cut = by_bucket(values >> np.uint64(COUNT_BITS - 32), buckets)
            out = [(*[None] * 6, b, pressed(values[lo:hi]), zstandard.compress(counts[lo:hi].astype(np.uint32).tobytes(), 1)) for b, lo, hi in zip(found.tolist(), cut[:-1].tolist(), cut[1:].tolist(), strict=True)]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names)

        for batch in batches:
            data, offs = text_spans(batch.column(2))
            n, digests, sets, keys = [], [], [], []
            for lo, hi in doc_chunks(offs):
                digests += map(xxhash.xxh3_128_digest, plain_texts(data, offs[lo : hi + 1]))
            for own in sets_of(data, offs):
                n.append(len(own))
                sets.append(xxhash.xxh3_128_digest(own.tobytes()))
                keys.append(min_wise(own))
                if len(own) and sets[-1] not in seen:  # copies count once in a task
                    seen.add(sets[-1])
                    held.append(own >> shift)
                    size += len(own)
                if size >= COUNT_CHUNK:
                    yield flush()
                    held, size = [], 0
            none = len(n)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(c, t) for c, t in zip((n, digests, sets, keys), types[2:6], strict=True)), *(pa.nulls(none, t) for t in types[6:])], names)
        if held:
            yield flush()

    return rows.mapInArrow(run, "rid long, doc_id long, n long, digest binary, set binary, keys array<long>, bucket long, values binary, counts binary")


class Order:
    """The global order of shingles, told to all tasks in bounded size: which shingles are
    shared (a Bloom filter; a false one is only moved back) and how often the most frequent
    ones occur.  It is a function of the hash alone, so it is the same for every set."""

    def __init__(self, shared: IdFilter, frequent: np.ndarray, counts: np.ndarray):
        self.shared, self.frequent, self.counts = shared, frequent, counts

    def arranged(self, own: np.ndarray) -> np.ndarray:
        """Sorted hashes of a set, rare ones first, then shared ones by count."""
        short = own >> np.uint64(64 - COUNT_BITS)
        often = self.shared.test(short)
        last = np.flatnonzero(often)
        if not len(last):
            return own
        if len(self.frequent):
            at = np.searchsorted(self.frequent, short[last])
            known = np.take(self.frequent, at, mode="clip") == short[last]
            count = np.where(known, np.take(self.counts, at, mode="clip"), 0)
            last = last[np.lexsort((own[last], count))]
        return np.concatenate((own[~often], own[last]))


def shingle_order(s: Scratch, blobs: DataFrame, shared: int, frequent: int, most: int) -> Order:
    """Counts every truncated hash over all sets, task by task and then bucket by bucket."""

    @lean
    def total(t: pa.Table) -> pa.Table:
        parts = [(unpressed(v), np.frombuffer(zstandard.decompress(c), np.uint32)) for v, c in zip(t.column("values").to_pylist(), t.column("counts").to_pylist(), strict=True)]
        values = np.concatenate([v for v, _ in parts])
        order = np.argsort(values, kind="stable")
        values, counts = values[order], np.concatenate([c for _, c in parts])[order].astype(np.int64)
        first = np.flatnonzero(np.concatenate(([True], values[1:] != values[:-1])))
        sums = np.add.reduceat(counts, first)
        keep = sums >= shared
        return pa.table({"value": pa.array(values[first][keep].astype(np.int64)), "count": pa.array(sums[keep])})

    found = s.save(blobs.groupBy("bucket").applyInArrow(total, "value long, count long"), "shared")
    while (n := found.where(F.col("count") >= shared).count()) > SHARED_MOST:
        shared *= 2
    often = found.where(F.col("count") >= max(shared, frequent)).orderBy(F.desc("count"), "value").limit(most).toPandas().sort_values("value")
    return Order(IdFilter.of(found.where(F.col("count") >= shared), "value", n), often["value"].to_numpy(np.uint64), often["count"].to_numpy(np.int64))


def prefix(own: np.ndarray, order: Order, threshold: int) -> np.ndarray:
    """The first shingles of a set in the global order; two similar sets share one of them."""
    n = len(own)
    return order.arranged(own)[: n - -(-threshold * n // 100) + 1]


def posting_lists(rows: DataFrame, classes: IdFilter, arrange: Order, buckets: int, threshold: int) -> DataFrame:
    """``key, rid, n, pos`` of all index lists with two sets or more."""

    @lean
    def emit(batches):
        names = ["bucket", "keys", "rids", "ns", "poss"]

        def flush(held):
            keys = np.concatenate([k for _, _, k in held])
            lens = [len(k) for _, _, k in held]
            rids, ns = np.repeat(np.array([r for r, _, _ in held], np.int64), lens), np.repeat(np.array([n for _, n, _ in held], np.int32), lens)
            pos = np.concatenate([np.arange(m, dtype=np.int32) for m in lens])
            order = np.argsort(keys)
            keys = keys[order]
            found, cut = by_bucket(keys >> np.uint64(32), buckets)
            out = []
            for b, lo, hi in zip(found.tolist(), cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                o = order[lo:hi]
                out.append((b, pressed(keys[lo:hi]), rids[o].tobytes(), ns[o].tobytes(), pos[o].tobytes()))
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if k == 0 else pa.binary()) for k, c in enumerate(zip(*out, strict=True))], names)

        held, size = [], 0
        for batch in batches:
            batch = batch.filter(pa.array(classes.test(batch.column(0).to_numpy(zero_copy_only=False))))
            data, offs = text_spans(batch.column(1))
            for rid, own in zip(batch.column(0).to_pylist(), sets_of(data, offs), strict=True):
                if len(own):
                    held.append((rid, len(own), prefix(own, arrange, threshold)))
                    size += len(held[-1][2])
                if size >= COUNT_CHUNK // 2:
                    yield flush(held)
                    held, size = [], 0
        if held:
            yield flush(held)

    @lean
    def lists(t: pa.Table) -> pa.Table:
        columns = {"key": np.concatenate([unpressed(b) for b in t.column("keys").to_pylist()])}
        for name, blob, kind in (("rid", "rids", np.int64), ("n", "ns", np.int32), ("pos", "poss", np.int32)):
            columns[name] = np.concatenate([np.frombuffer(b, kind) for b in t.column(blob).to_pylist()])
        order = np.argsort(columns["key"], kind="stable")
        keys = columns["key"][order]
        same = keys[1:] == keys[:-1]
        several = order[np.concatenate((same, [False])) | np.concatenate(([False], same))]
        return pa.table({"key": columns["key"][several].view(np.int64), "rid": columns["rid"][several], "n": columns["n"][several], "pos": columns["pos"][several]})

    blobs = rows.select("rid", "text").mapInArrow(emit, "bucket long, keys binary, rids binary, ns binary, poss binary")
    return blobs.groupBy("bucket").applyInArrow(lists, "key long, rid long, n int, pos int")


def list_pairs(rid, n, pos, comp, part, threshold: int):
    """Candidate pairs of one index list, its entries ordered by size and position.

    Pairs of one component are skipped, and of one part where several are given.
    """
    m = len(rid)
    if m == 2:
        if comp[0] == comp[1] or (part is not None and part[0] == part[1]) or 100 * int(n[0]) < threshold * int(n[1]):
            return
        need = -(-threshold * int(n[0] + n[1]) // (100 + threshold))
        if min(n[0] - pos[0], n[1] - pos[1]) >= need:
            yield rid[:1], rid[1:]
        return
    blocks = np.flatnonzero(np.concatenate(([True], n[1:] != n[:-1], [True])))
    sizes = n[blocks[:-1]].astype(np.int64)
    for i in range(m):
        own = int(n[i])
        # sizes from this one up to the largest that can reach the threshold
        first, last = int(np.searchsorted(sizes, own)), int(np.searchsorted(sizes, own * 100 // threshold, "right"))
        for b in range(first, last):
            lo, hi = max(int(blocks[b]), i + 1), int(blocks[b + 1])
            need = -(-threshold * (own + int(sizes[b])) // (100 + threshold))
            if own - int(pos[i]) < need or lo >= hi:
                continue
            # behind this position too few shingles remain: skip the rest of the block
            hi = lo + int(np.searchsorted(pos[lo:hi], int(sizes[b]) - need, "right"))
            others = comp[lo:hi] != comp[i]
            if part is not None:
                others &= part[lo:hi] != part[i]
            others = np.flatnonzero(others) + lo
            if len(others):
                yield np.full(len(others), rid[i]), rid[others]


def candidates(lists: DataFrame, threshold: int, tile: int = TILE_ROWS) -> DataFrame:
    """Pairs of sets of different components that the index can't rule out.

    A list with more than ``tile`` entries is dealt over parts by a hash of the set, and
    every two parts meet in a task of their own.
    """
    mixed = lists.groupBy("key").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.ceil(F.count("*") / tile).alias("tiles")).where("lo < hi").select("key", "tiles")
    parted = lists.join(mixed, "key").withColumn("part", F.pmod(F.xxhash64("rid"), F.col("tiles")))
    parted = parted.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("tiles") - 1)))
    parted = parted.select("key", F.least("part", "other").alias("one"), F.greatest("part", "other").alias("two"), "rid", "n", "pos", "comp", "part")
    dealt = parted.repartition("key", "one", "two").sortWithinPartitions("key", "one", "two", "n", "pos", "rid")

    @lean
    def run(batches):
        def pairs(cols):
            key, one, two = cols[:3]
            cuts = np.flatnonzero(starts(key, one, two, [True]))
            left, right = [], []
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                rid, n, pos, comp, part = (c[a:b] for c in cols[3:])
                for x, y in list_pairs(rid, n, pos, comp, part if one[a] != two[a] else None, threshold):
                    left.append(x)
                    right.append(y)
            if left:
                x, y = np.concatenate(left), np.concatenate(right)
                both = np.unique(np.stack([np.minimum(x, y), np.maximum(x, y)]), axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(both[0]), pa.array(both[1])], ["a", "b"])

        def starts(key, one, two, end):
            return np.concatenate(([True], (key[1:] != key[:-1]) | (one[1:] != one[:-1]) | (two[1:] != two[:-1]), end))

        rest = None
        for batch in batches:
            cols = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            if rest is not None:
                cols = [np.concatenate(p) for p in zip(rest, cols, strict=True)]
            if not len(cols[0]):
                continue
            cut = int(np.flatnonzero(starts(*cols[:3], []))[-1])  # the last list may go on
            if cut:
                yield from pairs([c[:cut] for c in cols])
            rest = [c[cut:] for c in cols]
        if rest is not None and len(rest[0]):
            yield from pairs(rest)

    return dealt.mapInArrow(run, "a long, b long").distinct()


def verified(s: Scratch, rows: DataFrame, pairs: DataFrame, threshold: int, name: str) -> DataFrame:
    """``a, b, n_a, n_b, common, linked`` of all pairs ``(a, b)``: the common shingles, and
    whether the sets of words are similar enough.

    Each text is sent to the tasks of the leaders it is compared with; a leader with many
    members is sent to several tasks.
    """
    pairs = s.save(pairs, f"{name}-pairs")
    sizes = pairs.groupBy("a").agg(F.ceil(F.count("*") / SALT_ROWS).alias("salts"))
    members = pairs.join(sizes, "a").select(F.col("a").alias("lead"), F.pmod(F.xxhash64("b"), F.col("salts")).alias("salt"), F.col("b").alias("rid"))
    leads = sizes.select(F.col("a").alias("lead"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1)).alias("salt"), F.col("a").alias("rid"))
    routes = s.save(members.union(leads), f"{name}-routes")
    wanted = IdFilter.of(routes, "rid", routes.agg(F.approx_count_distinct("rid")).first()[0])

    @lean
    def chosen(batches):
        for batch in batches:
            yield batch.filter(pa.array(wanted.test(batch.column(0).to_numpy(zero_copy_only=False))))

    sent = routes.join(rows.select("rid", F.col("text").cast("binary").alias("body")).mapInArrow(chosen, "rid long, body binary"), "rid")
    dealt = sent.withColumn("member", F.col("rid") != F.col("lead")).repartition("lead", "salt").sortWithinPartitions("lead", "salt", "member")

    @lean
    def compare(batches):
        lead, own = None, None
        for batch in batches:
            out = []
            bodies = batch.column(3)
            for k, (at, salt, rid) in enumerate(zip(*(batch.column(c).to_pylist() for c in (0, 1, 2)), strict=True)):
                text = Words(bodies[k].as_buffer())
                if rid == at:
                    lead, own = (at, salt), text
                    continue
                assert lead == (at, salt)
                common, linked = similar(own, text, threshold)
                out.append((at, rid, len(own.set), len(text.set), common, linked))
            cols = list(zip(*out, strict=True)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if k < 5 else pa.bool_()) for k, c in enumerate(cols)], ["a", "b", "n_a", "n_b", "common", "linked"])

    got = dealt.select("lead", "salt", "rid", "body").mapInArrow(compare, "a long, b long, n_a long, n_b long, common long, linked boolean")
    return s.save(got, f"{name}-answers")


def derived(s: Scratch, rows: DataFrame, pairs: DataFrame, led: DataFrame, threshold: int) -> tuple[DataFrame, DataFrame]:
    """The links among leaders of candidate ``pairs (a, b)``, and the other pairs with what
    their leaders have in ``common`` and what both add (``more``).

    ``led``: answers of the leaders.  A set close to one stands behind it with the number
    of shingles that it has beyond it; two sets have at most as many in common as their
    leaders have, and those, so most pairs need not be compared themselves.
    """
    behind = led.where("linked").groupBy(F.col("b").alias("rid")).agg(F.max_by(F.struct("a", (F.col("n_b") - F.col("common")).alias("more"), F.col("n_b").alias("n")), F.struct("common", "a")).alias("l"))
    behind = s.save(behind.select("rid", F.col("l.a").alias("lead"), "l.more"), "behind")

    def ends(x: DataFrame, side: str) -> DataFrame:
        own = behind.select(F.col("rid").alias(side), F.col("lead").alias(f"lead_{side}"), F.col("more").alias(f"more_{side}"))
        return x.join(own, side, "left").withColumns({f"lead_{side}": F.coalesce(f"lead_{side}", side), f"more_{side}": F.coalesce(f"more_{side}", F.lit(0).cast("long"))})

    placed = ends(ends(pairs, "a"), "b")
    placed = placed.withColumn("p", F.least("lead_a", "lead_b")).withColumn("q", F.greatest("lead_a", "lead_b"))
    placed = s.save(placed.select("a", "b", "p", "q", (F.col("more_a") + F.col("more_b")).alias("more"), ((F.col("lead_a") == F.col("a")) & (F.col("lead_b") == F.col("b"))).alias("own")), "placed")
    answers = verified(s, rows, placed.where("p < q").select(F.col("p").alias("a"), F.col("q").alias("b")).distinct(), threshold, "bases")
    known = answers.select(F.col("a").alias("p"), F.col("b").alias("q"), "n_a", "n_b", "common", "linked")
    return answers.where("linked"), placed.where("NOT own").join(known, ["p", "q"], "left")


def leader_pairs(sets: DataFrame) -> DataFrame:
    """Sets with the first and the last set that share several of their keys."""
    keys = sets.select("rid", "n", F.size("keys").alias("own"), F.explode("keys").alias("key"))
    leads = keys.groupBy("key").agg(F.min(F.struct("rid", "n")).alias("first"), F.max(F.struct("rid", "n")).alias("last")).where("first.rid < last.rid")
    both = keys.join(leads, "key").select("rid", "n", "own", F.explode(F.array("first", "last")).alias("lead")).where("rid <> lead.rid")
    fits = F.least("n", "lead.n") * 100 >= F.greatest("n", "lead.n") * THRESHOLD
    shared = both.where(fits).groupBy(F.col("lead.rid").alias("a"), F.col("rid").alias("b")).agg(F.count("*").alias("keys"), F.max("own").alias("own"))
    return shared.where(F.col("keys") >= F.least(F.lit(KEYS_SHARED), F.col("own"))).select("a", "b")


def join_components(s: Scratch, docs: DataFrame, threshold: int = THRESHOLD, shared: int = SHARED, frequent: int = FREQUENT, most: int = FREQUENT_MOST, tile: int = TILE_ROWS) -> DataFrame:
    """``rid, doc_id, n_shingles, component_id, first_rid`` of every document."""
    rows = keyed(s, docs)
    buckets = max(1, rows.count() // BUCKET_DOCS)
    both = s.save(summaries(rows, buckets), "summaries")
    sets = s.save(both.where("bucket IS NULL").select("rid", "doc_id", "n", "digest", "set", "keys"), "sets")
    arrange = shingle_order(s, both.where("bucket IS NOT NULL").select("bucket", "values", "counts"), shared, frequent, most)
    s.drop("summaries")
    classes = s.save(sets.where("n > 0").groupBy("digest").agg(F.min_by(F.struct("rid", "n", "set", "keys"), "rid").alias("c")).select("c.*", "digest"), "classes")
    first = classes.groupBy("set").agg(F.min_by(F.struct("rid", "n", "keys"), "rid").alias("c")).select("c.*", "set")
    first = s.save(first, "representatives")
    twins = classes.select("set", F.col("rid").alias("b")).join(first.select("set", F.col("rid").alias("a")), "set").where("a <> b").select("a", "b")
    led = verified(s, rows, leader_pairs(first).union(twins), threshold, "lead")
    leaders = led.where("linked").select("a", "b")
    near = s.save(components(s, leaders), "near")
    # a set that equals its representative's in hashes alone stands for itself
    odd = twins.join(led.where("linked"), ["a", "b"], "left_anti").select(F.col("b").alias("rid"))
    indexed = first.select("rid").union(odd).join(near, "rid", "left").withColumn("comp", F.coalesce("comp", "rid"))
    indexed = s.save(indexed, "indexed")
    lists = posting_lists(rows, IdFilter.of(indexed, "rid", indexed.count()), arrange, buckets, threshold)
    lists = s.save(lists.join(indexed, "rid"), "lists")
    answers, open_ = derived(s, rows, candidates(lists, threshold, tile), led, threshold)
    n = first.select("rid", "n").union(odd.join(classes, "rid").select("rid", "n"))
    open_ = open_.join(n.select(F.col("rid").alias("a"), F.col("n").alias("size_a")), "a").join(n.select(F.col("rid").alias("b"), F.col("n").alias("size_b")), "b")
    enough = F.col("common").isNull() | ((100 + threshold) * (F.col("common") + F.col("more")) >= threshold * (F.col("size_a") + F.col("size_b")))
    rest = verified(s, rows, open_.where(enough).select("a", "b"), threshold, "rest").where("linked")
    copies = sets.where("n > 0").join(classes.select("digest", F.col("rid").alias("lead")), "digest")
    comps = components(s, leaders.union(answers.select("a", "b")).union(rest.select("a", "b")).union(copies.where("rid <> lead").select(F.col("lead").alias("a"), F.col("rid").alias("b"))))
    found = s.save(sets.select("rid", "doc_id", F.col("n").alias("n_shingles")).join(comps, "rid", "left"), "found")
    if not found.where("doc_id IS NULL OR doc_id <> rid").limit(1).count():  # the row key is the id
        done = found.withColumn("component_id", F.coalesce("comp", "rid"))
    else:
        least = found.where("comp IS NOT NULL").groupBy("comp").agg(F.min("doc_id").alias("least"))
        least = least.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        done = found.withColumn("salt", F.pmod("rid", F.lit(SALTS)).cast("int")).join(least, ["comp", "salt"], "left").withColumn("component_id", F.coalesce("least", "doc_id"))
    return s.keep(done.select("rid", "doc_id", "n_shingles", "component_id", F.coalesce("comp", "rid").alias("first_rid")))
