"""Exact substring dedup with suffix arrays.

A byte is removed if a string of LENGTH bytes that covers it starts anywhere else too.

Every such string holds a content-chosen anchor (the leftmost smallest hash of its k-byte
grams), so both of its copies lie in windows around anchors of equal hash.  The windows of
an anchor hash are put in one shard, equal windows as one with their count; a shard's
windows are concatenated and its suffix array is built by Larsson-Sadakane refinement, its
common prefixes by Kasai's rule, both vectorised.  Shards above a size are cut up, and the
suffix arrays of their parts are merged by binary search.  Suffixes whose common prefix
reaches LENGTH form a run; a run of two places or more marks its strings as repeated.

Whether two windows, or two whole texts, are equal is told by cryptographic digests of
their bytes (128 bits of BLAKE2b, SHA-256), never by the rolling hash that finds anchors.
A window that comes again as a whole is repeated by that alone; it enters a shard only
where some other window has the same anchor.

Defined results: null texts are empty; texts shorter than LENGTH keep all their bytes;
repeated rows, and rows without an id, are documents of their own and as copies of each
other lose every byte if they are long enough; an empty table gives no rows; other columns
are not read, whatever their names; a long text is searched for anchors piece by piece,
with pieces that overlap, so memory doesn't grow with it but for its own bytes.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.llm.common import CHUNK_BYTES, IdFilter, Scratch, doc_chunks, keyed, lean, mixed, text_spans
from gridlake.llm.textkernels import _VALUE, _tables

LENGTH = 200
#: Bytes of a gram: long enough that common words alone don't make one.
GRAM = 64
#: Window bytes in a shard, about, and in a part of one at most.
SHARD_BYTES, PART_BYTES = 1 << 20, 2 << 20
#: Documents whose anchors make one group.
BUCKET_DOCS = 2048
#: Anchors that a task sorts at once.
FLUSH = 1 << 19
_RAW = _VALUE.copy()
_RAW[65:91] = mixed(_VALUE[97:123])  # here case counts


def anchors(data: np.ndarray, offsets: np.ndarray, length: int = LENGTH, gram: int = GRAM):
    """``(text number, position, anchor hash)`` of all anchors of texts of a few MB at most."""
    base, n = int(offsets[0]), int(offsets[-1] - offsets[0])
    empty = (np.zeros(0, np.int64),) * 2 + (np.zeros(0, np.uint64),)
    if n < length:
        return empty
    data, offs = data[base : base + n], offsets - base
    power, inverse = _tables(n + 1)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(_RAW[data] * power[:n], out=total[1:])
    hashes = mixed((total[gram:] - total[:-gram]) * inverse[: n - gram + 1])
    bits = np.uint64(24)  # of a place; the order of hashes must not depend on the piece
    ranked = (hashes >> bits << bits) | np.arange(len(hashes), dtype=np.uint64)
    low = _window_min(ranked, length - gram + 1)
    doc_of = np.repeat(np.arange(len(offs) - 1), np.diff(offs))
    starts = np.arange(n - length + 1)
    low = low[starts[starts + length <= offs[doc_of[starts] + 1]]]
    if not len(low):
        return empty
    at = np.unique(low[np.concatenate(([True], low[1:] != low[:-1]))] & np.uint64((1 << int(bits)) - 1)).astype(np.int64)
    doc = doc_of[at]
    return doc, at - offs[doc], hashes[at]


def all_anchors(data: np.ndarray, offsets: np.ndarray, chunk: int = CHUNK_BYTES):
    """The same for one text of any length, or several within ``chunk`` bytes."""
    lo, hi = int(offsets[0]), int(offsets[-1])
    if hi - lo <= chunk or len(offsets) > 2:
        return anchors(data, offsets)
    parts = []
    for a in range(lo, hi, chunk):  # every string of LENGTH bytes lies inside one piece
        _, at, h = anchors(data, np.array([a, min(hi, a + chunk + LENGTH - 1)]))
        parts.append((at + (a - lo), h))
    at, first = np.unique(np.concatenate([p for p, _ in parts]), return_index=True)
    return np.zeros(len(at), np.int64), at, np.concatenate([h for _, h in parts])[first]


def window_digests(data: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Two numbers for the bytes of every window, from a cryptographic digest."""
    raw = memoryview(np.ascontiguousarray(data))
    return np.frombuffer(b"".join(hashlib.blake2b(raw[a:b], digest_size=16).digest() for a, b in zip(lo.tolist(), hi.tolist(), strict=True)), np.uint64).reshape(-1, 2)


def _window_min(x: np.ndarray, w: int) -> np.ndarray:
    """The least of every ``w`` values in a row, by prefix and suffix minima of blocks."""
    n = len(x) - w + 1
    pad = np.full(-len(x) % w, np.iinfo(x.dtype).max, x.dtype)
    blocks = np.concatenate((x, pad)).reshape(-1, w)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[w - 1 : w - 1 + n])


def merged(starts: np.ndarray, stops: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The union of half-open intervals as maximal runs."""
    if not len(starts):
        return starts, stops
    order = np.argsort(starts, kind="stable")
    starts, reach = starts[order], np.maximum.accumulate(stops[order])
    new = np.concatenate(([True], starts[1:] > reach[:-1]))
    last = np.concatenate((np.flatnonzero(new)[1:] - 1, [len(starts) - 1]))
    return starts[new], reach[last]


#: From here on a number needs one byte more.
_BYTES = np.array([1 << (8 * k) for k in range(8)], np.uint64)

# --- suffix arrays -----------------------------------------------------------------


def words_at(text: np.ndarray) -> np.ndarray:
    """The eight bytes from every position as one number that sorts like them."""
    padded = np.concatenate((text, np.zeros(8, np.uint8)))
    out = np.zeros(len(text), np.uint64)
    for k in range(8):
        out = (out << np.uint64(8)) | padded[k : k + len(text)]
    return out


def suffix_array(text: np.ndarray, key: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes sorted by their first ``limit`` bytes or more, and their ranks.

    Larsson-Sadakane: a rank is the place of the group's first member, groups of one are
    done, and only the others are sorted again by the rank ``depth`` bytes further on.
    """
    n = len(text)
    sa = np.argsort(key, kind="stable")
    sorted_key = key[sa]
    head = np.concatenate(([True], sorted_key[1:] != sorted_key[:-1]))
    rank = np.empty(n, np.int64)
    rank[sa] = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    depth = 8
    while depth < limit:
        single = head & np.concatenate((head[1:], [True]))
        places = np.flatnonzero(~single)
        if not len(places):
            break
        p = sa[places]
        further = np.where(p + depth < n, rank[np.minimum(p + depth, n - 1)] + 1, 0)
        both = (rank[p] << 32) | further
        order = np.argsort(both, kind="stable")
        sa[places] = p = p[order]
        both = both[order]
        new = np.concatenate(([True], both[1:] != both[:-1]))
        head[places] = new
        rank[p] = np.maximum.accumulate(np.where(new, places, 0))
        depth *= 2
    return sa, rank


def common_prefixes(key: np.ndarray, sa: np.ndarray, rank: np.ndarray, starts: np.ndarray, lanes: np.ndarray, counts: np.ndarray, limit: int) -> np.ndarray:
    """Common prefix, capped at ``limit``, of each of the sorted suffixes and the one before.

    Kasai's rule: going through the text in order, a suffix shares at least one byte less
    with its predecessor than the suffix one byte before did.  All windows take their steps
    together: ``lanes`` are their first positions, ``counts`` how many suffixes of each are
    in ``sa``, which holds those marked in ``starts``.  Suffixes of equal rank were left
    unsorted: they share the limit, and nothing follows from them for the suffix behind;
    neither does it from a predecessor whose next suffix is not in ``sa``.
    """
    n = len(key)
    before = np.full(n, -1, np.int32)
    before[sa[1:]] = sa[:-1]
    shared = np.zeros(n, np.int16)
    order = np.argsort(-counts, kind="stable")
    lanes, counts = lanes[order], counts[order]
    h, free = np.zeros(len(lanes), np.int64), np.zeros(len(lanes), bool)
    for j in range(int(counts.max(initial=0))):
        m = int(np.searchsorted(-counts, -j))  # lanes with more than j suffixes
        p = lanes[:m] + j
        q = before[p].astype(np.int64)
        known = q >= 0
        h = np.where(known & free[:m], np.maximum(h[:m] - 1, 0), 0)
        tied = known & (rank[p] == rank[q])
        h[tied] = limit
        active = np.flatnonzero(known & (h < limit))
        while len(active):
            differ = key[p[active] + h[active]] ^ key[q[active] + h[active]]
            same = 8 - np.searchsorted(_BYTES, differ, "right")
            h[active] += same
            active = active[(same == 8) & (h[active] < limit)]
        h = np.minimum(h, limit)
        shared[p] = h
        free = known & ~tied & starts[np.minimum(q + 1, n - 1)]
    return shared[sa]


def compare(x: np.ndarray, xk: np.ndarray, p: np.ndarray, y: np.ndarray, yk: np.ndarray, q: np.ndarray, limit: int) -> np.ndarray:
    """Sign of ``x[p:p+limit]`` against ``y[q:q+limit]``; all of them lie inside."""
    sign = np.zeros(len(p), np.int64)
    active, at = np.arange(len(p)), 0
    while len(active) and at < limit:
        at = min(at, limit - 8)
        a, b = xk[p[active] + at], yk[q[active] + at]
        sign[active] = np.where(a < b, -1, np.where(a > b, 1, 0))
        active = active[a == b]
        at += 8
    return sign


class Part:
    """Concatenated windows with their suffix array."""

    def __init__(self, windows: list[bytes], places: np.ndarray, limit: int):
        """``places``: a number of each window's first byte's place; of later bytes it
        counts up, and equal places are the same byte of the same document."""
        lens = np.array([len(w) for w in windows], np.int64)
        self.text = np.frombuffer(b"\xff".join(windows) + b"\xff", np.uint8)
        self.begin = np.concatenate(([0], np.cumsum(lens + 1)[:-1]))
        self.window = np.repeat(np.arange(len(windows)), lens + 1)
        offset = np.arange(len(self.text)) - self.begin[self.window]
        #: Positions where a string of ``limit`` bytes starts.
        self.starts = offset + limit <= lens[self.window]
        self.offset, self.place = offset, places[self.window] + offset.astype(np.uint64)
        self.key = words_at(self.text)
        sa, rank = suffix_array(self.text, self.key, limit)
        #: The sorted suffixes that hold a whole string, numbered by runs that share it.
        self.sa = sa[self.starts[sa]]
        shared = common_prefixes(self.key, self.sa, rank, self.starts, self.begin, np.maximum(0, lens - limit + 1), limit)
        self.run = np.cumsum(shared < limit)


def repeated(windows: list[bytes], places: np.ndarray, several: np.ndarray, limit: int = LENGTH, part_bytes: int = PART_BYTES) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """For each window with some: its number and the runs of bytes in repeated strings.

    ``several``: windows that stand for more than one place.
    """
    size = np.cumsum([len(w) for w in windows])
    cut = [0, *(np.searchsorted(size, np.arange(part_bytes, size[-1], part_bytes)) + 1).tolist(), len(windows)] if size[-1] > part_bytes else [0, len(windows)]
    cut = sorted(set(cut))
    parts = [Part(windows[a:b], places[a:b], limit) for a, b in zip(cut[:-1], cut[1:], strict=True)]
    flags = []
    for part, a in zip(parts, cut[:-1], strict=True):
        mark = np.zeros(len(part.text), bool)
        if len(part.sa):
            first = np.flatnonzero(np.concatenate(([True], part.run[1:] != part.run[:-1])))
            place = part.place[part.sa]
            low, high = np.minimum.reduceat(place, first), np.maximum.reduceat(place, first)
            many = np.maximum.reduceat(several[a + part.window[part.sa]], first)
            size = np.diff(np.concatenate((first, [len(part.sa)])))
            mark[part.sa[np.repeat((low != high) | many, size)]] = True
            part.heads, part.low, part.high = part.sa[first], low, high
            part.sizes = size
        else:
            part.heads = part.low = part.high = part.sizes = np.zeros(0, np.int64)
        flags.append(mark)
    for i, x in enumerate(parts):  # one head of each run of one part is searched in the other's
        for j in range(i + 1, len(parts)):
            y = parts[j]
            if not len(x.heads) or not len(y.heads):
                continue
            lo, hi = np.zeros(len(y.heads), np.int64), np.full(len(y.heads), len(x.heads), np.int64)
            while (open_ := np.flatnonzero(lo < hi)).size:
                mid = (lo[open_] + hi[open_]) // 2
                less = compare(x.text, x.key, x.heads[mid], y.text, y.key, y.heads[open_], limit) < 0
                lo[open_[less]], hi[open_[~less]] = mid[less] + 1, mid[~less]
            hit = np.flatnonzero(lo < len(x.heads))
            hit = hit[compare(x.text, x.key, x.heads[lo[hit]], y.text, y.key, y.heads[hit], limit) == 0]
            other = lo[hit]
            apart = (np.minimum(x.low[other], y.low[hit]) != np.maximum(x.high[other], y.high[hit]))
            for part, runs, flag in ((x, other[apart], flags[i]), (y, hit[apart], flags[j])):
                first = np.concatenate(([0], np.cumsum(part.sizes)))
                for r in runs.tolist():
                    flag[part.sa[first[r] : first[r + 1]]] = True
    out = []
    for part, a, mark in zip(parts, cut[:-1], flags, strict=True):
        at = np.flatnonzero(mark)
        if not len(at):
            continue
        own = part.window[at]
        first = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1], [True])))
        for lo, hi in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
            s = part.offset[at[lo:hi]]
            out.append((a + int(own[lo]), *merged(s, s + limit)))
    return out


# --- the operator ------------------------------------------------------------------

_DOC = "rid long, doc_id long, n_bytes long, sha256 string"
_BLOB = "bucket long, anchors binary, windows binary, rids binary, positions binary, counts binary, ends binary"


def _scan(rows: DataFrame, buckets: int) -> DataFrame:
    """Document rows, and blobs of anchors by bucket; equal windows of a text are one entry."""

    @lean
    def run(batches):
        names = [x.split()[0] for x in f"{_DOC}, {_BLOB}".split(", ")]
        types = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), *[pa.binary()] * 6]
        seen: set[str] = set()
        held, size = [], 0

        def flush():
            h, w, r, p, c, e = (np.concatenate(x) for x in zip(*held, strict=True))
            bucket = (mixed(h) % np.uint64(buckets)).astype(np.int64)
            order = np.argsort(bucket, kind="stable")
            own = bucket[order]
            cut = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1], [True]))).tolist()
            out = [(*[None] * 4, int(own[lo]), *(x[order[lo:hi]].tobytes() for x in (h, w, r, p, c, e))) for lo, hi in zip(cut[:-1], cut[1:], strict=True)]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names)

        for batch in batches:
            data, offs = text_spans(batch.column(2))
            raw, rids = memoryview(data), batch.column(0).to_numpy(zero_copy_only=False)
            shas = [hashlib.sha256(raw[a:b]).hexdigest() for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(np.diff(offs)), pa.array(shas), *(pa.nulls(len(shas), t) for t in types[4:])], names)
            new = np.array([d not in seen and not seen.add(d) for d in shas], bool)
            for lo, hi in doc_chunks(offs, CHUNK_BYTES):
                doc, at, h = all_anchors(data, offs[lo : hi + 1])
                keep = new[lo:hi][doc]
                doc, at, h = doc[keep], at[keep], h[keep]
                if not len(doc):
                    continue
                begin = offs[lo:hi][doc]
                w = window_digests(data, np.maximum(begin, begin + at - (LENGTH - GRAM)), np.minimum(offs[lo + 1 : hi + 1][doc], begin + at + LENGTH))
                order = np.lexsort((at, w[:, 1], w[:, 0], h, doc))
                doc, at, h, w = doc[order], at[order], h[order], w[order]
                # equal windows that overlap form one entry from the first to the last
                same = (doc[1:] == doc[:-1]) & (h[1:] == h[:-1]) & (w[1:] == w[:-1]).all(1) & (at[1:] - at[:-1] <= LENGTH)
                first = np.flatnonzero(np.concatenate(([True], ~same)))
                count = np.diff(np.concatenate((first, [len(doc)])))
                held.append((h[first], w[first], rids[lo:hi][doc[first]].astype(np.int64), at[first], count, at[first + count - 1]))
                size += len(first)
                if size >= FLUSH:
                    yield flush()
                    held, size = [], 0
        if held:
            yield flush()

    return rows.mapInArrow(run, f"{_DOC}, {_BLOB}")


def _classified(blobs: DataFrame) -> DataFrame:
    """Anchors that occur again: ``rid, anchor, pos, last, full, asks``.

    full: the whole window occurs again.  asks: its text has to be compared, as some other
    window has the same anchor; of equal windows one asks.
    """

    @lean
    def run(t: pa.Table) -> pa.Table:
        kinds = {"anchors": np.uint64, "windows": np.uint64, "rids": np.int64, "positions": np.int64, "counts": np.int64, "ends": np.int64}
        h, w, r, p, c, e = (np.concatenate([np.frombuffer(b, k) for b in t.column(n).to_pylist()]) for n, k in kinds.items())
        w = w.reshape(-1, 2)
        order = np.lexsort((p, r, w[:, 1], w[:, 0], h))
        h, w, r, p, c, e = (x[order] for x in (h, w, r, p, c, e))
        new_h = np.concatenate(([True], h[1:] != h[:-1]))
        new_w = new_h | np.concatenate(([True], (w[1:] != w[:-1]).any(1)))
        first_w = np.flatnonzero(new_w)
        many_w = np.add.reduceat(c, first_w)
        full = np.repeat(many_w >= 2, np.diff(np.concatenate((first_w, [len(h)]))))
        first_h = np.flatnonzero(new_h)
        kinds_h = np.add.reduceat(new_w.astype(np.int64), first_h)
        mixed_h = np.repeat(kinds_h >= 2, np.diff(np.concatenate((first_h, [len(h)]))))
        asks = mixed_h & new_w
        # full windows are compared only where one that is not full could match them
        lone = np.repeat(np.logical_and.reduceat(full, first_h), np.diff(np.concatenate((first_h, [len(h)]))))
        asks &= ~lone
        keep = full | asks
        return pa.table({"rid": r[keep], "anchor": h[keep].view(np.int64), "pos": p[keep], "last": e[keep], "full": full[keep], "asks": asks[keep]})

    return blobs.groupBy("bucket").applyInArrow(run, "rid long, anchor long, pos long, last long, full boolean, asks boolean")


def _texts(rows: DataFrame, wanted: IdFilter) -> DataFrame:
    @lean
    def run(batches):
        for batch in batches:
            yield batch.filter(pa.array(wanted.test(batch.column(0).to_numpy(zero_copy_only=False))))

    return rows.select("rid", "text").mapInArrow(run, "rid long, text string")


def _windows(found: DataFrame, rows: DataFrame, wanted: IdFilter, shards: int) -> DataFrame:
    """The text of every window that asks, with its shard."""
    asked = found.where("asks").groupBy("rid").agg(F.collect_list(F.struct("anchor", "pos", "full")).alias("asked"))
    both = asked.join(_texts(rows, wanted), "rid").select("rid", "asked", F.col("text").cast("binary").alias("text"))

    @lean
    def run(batches):
        for batch in batches:
            out = []
            for k, (rid, asked) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
                text = memoryview(batch.column(2)[k].as_buffer())
                for a in asked:
                    lo, hi = max(0, a["pos"] - (LENGTH - GRAM)), min(len(text), a["pos"] + LENGTH)
                    out.append((int(np.int64(a["anchor"]).view(np.uint64)) % shards, rid, lo, a["full"], bytes(text[lo:hi])))
                if len(out) >= 20_000:
                    yield _window_batch(out)
                    out = []
            yield _window_batch(out)

    return both.mapInArrow(run, "shard long, rid long, start long, full boolean, body binary")


def _window_batch(out: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*out, strict=True)) or [[]] * 5
    types = (pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], ["shard", "rid", "start", "full", "body"])


def _shard_spans(windows: DataFrame) -> DataFrame:
    """``rid, start, stop``: what the suffix arrays of each shard mark in partly repeated windows."""

    @lean
    def run(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        rid, start, full = (t.column(c).to_numpy(zero_copy_only=False) for c in ("rid", "start", "full"))
        # consecutive numbers inside a document, far apart between documents
        places = mixed(rid.view(np.uint64) + np.uint64(1)) + start.astype(np.uint64)
        out: list[tuple[int, int, int]] = []
        for k, lo, hi in repeated(t.column("body").to_pylist(), places, full.astype(bool)):
            if not full[k]:
                out += [(int(rid[k]), int(start[k]) + a, int(start[k]) + b) for a, b in zip(lo.tolist(), hi.tolist(), strict=True)]
        cols = list(zip(*out, strict=True)) or [[]] * 3
        return pa.table([pa.array(c, pa.int64()) for c in cols], names=["rid", "start", "stop"])

    return windows.groupBy("shard").applyInArrow(run, "rid long, start long, stop long")


def repeated_spans(s: Scratch, docs: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Keyed rows, document rows (``copied``: another text is equal) and, for the texts
    that are not copies, ``rid, spans array<struct<start,stop>>`` (unmerged)."""
    rows = keyed(s, docs)
    buckets = max(1, rows.count() // BUCKET_DOCS)
    scanned = s.save(_scan(rows, buckets), "scanned")
    table = scanned.where("bucket IS NULL").select(*[x.split()[0] for x in _DOC.split(", ")])
    copies = table.groupBy("sha256").count().where("count > 1").select("sha256", F.lit(True).alias("copied"))
    table = s.save(table.join(copies, "sha256", "left").select("rid", "doc_id", "n_bytes", "sha256", F.coalesce("copied", F.lit(False)).alias("copied")), "table")
    found = s.save(_classified(scanned.where("bucket IS NOT NULL").select(*[x.split()[0] for x in _BLOB.split(", ")])), "found")
    s.drop("scanned")
    asking = found.where("asks")
    n = asking.count()
    ids = asking.agg(F.approx_count_distinct("rid")).first()[0]
    windows = _windows(found, rows, IdFilter.of(asking, "rid", ids), max(1, -(-n * (2 * LENGTH - GRAM) // SHARD_BYTES)))
    marked = _shard_spans(windows)
    whole = found.where("full").select("rid", F.greatest(F.lit(0).cast("long"), F.col("pos") - (LENGTH - GRAM)).alias("start"), (F.col("last") + LENGTH).alias("stop"))
    unique = table.where("NOT copied").select("rid")
    spans = whole.union(marked).join(unique, "rid", "left_semi").groupBy("rid").agg(F.collect_list(F.struct("start", "stop")).alias("spans"))
    return rows, table, s.save(spans, "spans")


def _kept(text: memoryview, spans: list[dict]) -> tuple[bytes, int, int]:
    """What remains of a text, the bytes removed and the number of removed runs."""
    lo, hi = merged(np.array([x["start"] for x in spans], np.int64), np.minimum(len(text), np.array([x["stop"] for x in spans], np.int64)))
    edges = [0, *np.stack([lo, hi], 1).ravel().tolist(), len(text)]
    return b"".join(bytes(text[a:b]) for a, b in zip(edges[::2], edges[1::2], strict=True)), int((hi - lo).sum()), len(lo)


def dedup(s: Scratch, docs: DataFrame, texts: bool = False) -> DataFrame:
    """``rid, doc_id, n_bytes, n_removed, n_spans, kept_sha256`` and, on request, ``kept``.

    ``kept`` is null where nothing was removed.  A character that lost a part of its
    bytes is left out of it as a whole.
    """
    rows, table, spans = repeated_spans(s, docs)
    wanted = IdFilter.of(spans, "rid", spans.count())

    @lean
    def cut(batches):
        for batch in batches:
            removed, runs, shas, kept = [], [], [], []
            for k, own in enumerate(batch.column(1).to_pylist()):
                body, n, m = _kept(memoryview(batch.column(2)[k].as_buffer()), own)
                removed.append(n)
                runs.append(m)
                shas.append(hashlib.sha256(body).hexdigest())
                kept.append(body.decode("utf-8", "ignore") if texts else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(removed, pa.int64()), pa.array(runs, pa.int64()), pa.array(shas, pa.string()), pa.array(kept, pa.string())], ["rid", "removed", "runs", "sha", "kept"])

    both = spans.join(_texts(rows, wanted), "rid").select("rid", "spans", F.col("text").cast("binary").alias("text"))
    done = both.mapInArrow(cut, "rid long, removed long, runs long, sha string, kept string")
    gone = F.col("copied") & (F.col("n_bytes") >= LENGTH)
    zero = F.lit(0).cast("long")
    return s.keep(
        table.join(done, "rid", "left").select(
            "rid", "doc_id", "n_bytes",
            F.when(gone, F.col("n_bytes")).otherwise(F.coalesce("removed", zero)).alias("n_removed"),
            F.when(gone, F.lit(1).cast("long")).otherwise(F.coalesce("runs", zero)).alias("n_spans"),
            F.when(gone, F.lit(hashlib.sha256(b"").hexdigest())).otherwise(F.coalesce("sha", "sha256")).alias("kept_sha256"),
            F.when(gone, F.lit("")).otherwise(F.col("kept")).alias("kept"),
        )
    )
