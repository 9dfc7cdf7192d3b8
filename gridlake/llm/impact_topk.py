"""Exact top-k by inner product over an impact-ordered index.

Vectors are dealt over blocks of some thousands by a hash.  In a block, every component
is quantised to a level; a posting segment holds the rows of one (dimension, level).  The
segments of all blocks are built once and written; a block's index is read by one task,
which answers all queries with it, the queries coming to it in blocks of their own.
For a query, segments are processed in descending order of their contribution.  Partial
scores and counts of processed dimensions bound every row from both sides; processing
stops only when the bounds prove that few rows can be among the best, and those are
scored again exactly.  The blocks' answers are merged by score and id.

Defined results: vectors that are null, empty or hold null or non-finite components take
no part, nor do rows without an id; shorter vectors count as padded with zeros; repeated
rows are candidates of their own; ties go to the smaller id; an empty table, or one without
an id divisible by the step, gives no rows; other columns are not read, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridlake.llm.common import Scratch

K = 5
BLOCK = 8192
QUERY_BLOCK = 256
#: Levels that a block's range of values is cut into, about.
LEVELS = 32
#: Portions that the order of segments is processed in; the bounds are tested between them.
BANDS = 16
PACKED = "block long, ids binary, dim int, vectors binary"
INDEX = f"{PACKED}, shift int, postings binary, segments binary"


def valid_vectors(table: DataFrame, scale: int = 256) -> DataFrame:
    """``rid, vec_id, x array<long>`` of the vectors that take part."""
    ok = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0)
    finite = F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v.cast("double")) & (F.abs(v.cast("double")) < float("inf")))
    whole = F.transform("embedding", lambda v: F.floor(v.cast("double") * scale))
    return table.where(ok).where(finite).select(F.xxhash64("vec_id", F.monotonically_increasing_id()).alias("rid"), F.col("vec_id").cast("long").alias("vec_id"), whole.alias("x"))


def packed(rows: DataFrame, blocks: int, index: bool = False) -> DataFrame:
    """One row for each block of about as many vectors, with its postings if asked for."""

    def pack(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        lists = t.column("x").to_pylist()
        dim = max(map(len, lists))
        m = np.zeros((len(lists), dim), np.int64)
        for row, x in zip(m, lists, strict=True):
            row[: len(x)] = x
        ids = np.stack([t.column("vec_id").to_numpy(), t.column("rid").to_numpy()])
        narrow = m.astype(np.int32) if np.abs(m).max(initial=0) < 2**31 else m
        out = {"block": pa.array([t.column("block")[0].as_py()], pa.int64()), "ids": pa.array([ids.tobytes()], pa.binary()), "dim": pa.array([dim], pa.int32()), "vectors": pa.array([narrow.tobytes()], pa.binary())}
        if index:
            own = ImpactIndex.build(m)
            out |= {"shift": pa.array([own.shift], pa.int32()), "postings": pa.array([own.postings.tobytes()], pa.binary()), "segments": pa.array([own.segments.tobytes()], pa.binary())}
        return pa.table(out)

    return rows.withColumn("block", F.pmod(F.col("rid"), F.lit(blocks))).groupBy("block").applyInArrow(pack, INDEX if index else PACKED)


def unpacked(ids: bytes, dim: int, vectors: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    both = np.frombuffer(ids, np.int64).reshape(2, -1)
    n = both.shape[1]
    kind = np.int32 if len(vectors) == 4 * n * dim else np.int64
    return both[0], both[1], np.frombuffer(vectors, kind).reshape(n, dim).astype(np.int64)


class ImpactIndex:
    """The posting segments of one block: ``segments`` has start, stop, dimension and level
    of each, ``postings`` the rows."""

    def __init__(self, vectors: np.ndarray, shift: int, postings: np.ndarray, segments: np.ndarray):
        self.vectors, self.shift, self.postings, self.segments = vectors, shift, postings, segments
        self.n, self.d = vectors.shape
        self.starts, self.stops, self.dims, levels = segments
        #: The middle of a segment's values, and how far from it they can be.
        self.half = ((1 << shift) - 1) / 2
        self.values = (levels << shift) + self.half

    @classmethod
    def build(cls, vectors: np.ndarray, levels: int = LEVELS) -> ImpactIndex:
        n, d = vectors.shape
        reach = int(vectors.max(initial=0)) - int(vectors.min(initial=0)) + 1
        shift = max(0, (reach // levels).bit_length() - 1)
        level = vectors >> shift
        postings, segments = [], []
        for j in range(d):
            order = np.argsort(level[:, j], kind="stable").astype(np.int32)
            own = level[order, j]
            cut = np.flatnonzero(np.diff(own)) + 1
            first, last = np.concatenate(([0], cut)), np.concatenate((cut, [n]))
            segments.append(np.stack([first + j * n, last + j * n, np.full(len(first), j), own[first]]))
            postings.append(order)
        return cls(vectors, shift, np.concatenate(postings), np.concatenate(segments, axis=1))

    def possible(self, query: np.ndarray, k: int) -> np.ndarray:
        """Rows that the bounds don't exclude from the ``k`` best; all of them if need be."""
        n, d = self.n, self.d
        impact = query[self.dims] * self.values
        order = np.argsort(-impact, kind="stable")
        impact, starts, lens = impact[order], self.starts[order], (self.stops - self.starts)[order]
        slack = float(np.abs(query).sum()) * self.half
        lowest = float(impact[-1])
        edges = np.searchsorted(np.cumsum(lens), np.linspace(0, n * d, BANDS + 1)[1:-1])
        edges = np.unique(np.concatenate(([0], edges, [len(order)])))
        score, seen = np.zeros(n), np.zeros(n)
        members = np.arange(n)
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            rows = np.concatenate([self.postings[s : s + m] for s, m in zip(starts[a:b].tolist(), lens[a:b].tolist(), strict=True)])
            score += np.bincount(rows, np.repeat(impact[a:b], lens[a:b]), minlength=n)
            seen += np.bincount(rows, minlength=n)
            if 2 * b < len(order):
                continue
            ahead = float(impact[b]) if b < len(order) else 0.0
            low = score + (d - seen) * lowest - slack
            high = score + (d - seen) * ahead + slack
            members = np.flatnonzero(high >= np.partition(low, n - k)[n - k]) if n > k else np.arange(n)
            if len(members) <= max(4 * k, n // 32):
                break
        return members

    def best(self, query: np.ndarray, k: int, ids: np.ndarray, rids: np.ndarray, own: int) -> list[tuple[int, int, int]]:
        """``(score, id, row key)`` of the ``k`` best rows but the query's own."""
        query = np.pad(query, (0, max(0, self.d - len(query))))[: self.d]
        rows = self.possible(query, k + 1)
        exact = self.vectors[rows] @ query
        order = np.lexsort((rids[rows], ids[rows], -exact))
        hits = [(int(exact[i]), int(ids[rows[i]]), int(rids[rows[i]])) for i in order[: k + 1].tolist()]
        return [h for h in hits if h[2] != own][:k]


def search(s: Scratch, table: DataFrame, every: int = 50, k: int = K, block: int = BLOCK, query_block: int = QUERY_BLOCK) -> DataFrame:
    """``query_id, rank, vec_id, score`` for the rows whose id is divisible by ``every``."""
    k_best = k
    vectors = s.save(valid_vectors(table), "vectors")
    asked = vectors.where(F.col("vec_id") % every == 0)
    n, m = vectors.count(), asked.count()
    blocks, query_blocks = max(1, -(-n // block)), max(1, -(-m // query_block))
    index = s.save(packed(vectors, blocks, index=True), "index")
    asks = s.save(packed(asked, query_blocks).drop("block"), "asks")
    # a stated query set against all rows: every block's index is followed by the queries
    reading = index.withColumn("asks", F.lit(0))
    asking = asks.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("block"), "*", F.lit(1).alias("asks"))
    visits = reading.unionByName(asking, allowMissingColumns=True).repartition(min(1 << 16, blocks), "block").sortWithinPartitions("block", "asks")

    def answer(batches):
        index = ids = rids = None
        for batch in batches:
            for k in range(batch.num_rows):
                r = batch.slice(k, 1).to_pylist()[0]
                if not r["asks"]:
                    ids, rids, m = unpacked(r["ids"], r["dim"], r["vectors"])
                    index = ImpactIndex(m, r["shift"], np.frombuffer(r["postings"], np.int32), np.frombuffer(r["segments"], np.int64).reshape(4, -1))
                    at = r["block"]
                    continue
                if index is None or at != r["block"]:  # no vector fell into this block
                    continue
                out = []
                for q, own, x in zip(*unpacked(r["ids"], r["dim"], r["vectors"]), strict=True):
                    out += [(int(q), int(own), *h) for h in index.best(x, k_best, ids, rids, int(own))]
                cols = list(zip(*out, strict=True)) or [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["query_id", "query_rid", "score", "vec_id", "vec_rid"])

    hits = visits.mapInArrow(answer, "query_id long, query_rid long, score long, vec_id long, vec_rid long")
    place = Window.partitionBy("query_id", "query_rid").orderBy(F.desc("score"), "vec_id", "vec_rid")
    return s.keep(hits.withColumn("rank", F.row_number().over(place)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score"))
