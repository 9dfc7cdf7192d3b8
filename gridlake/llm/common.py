"""Shared plumbing of the training-data operators.

* ``Scratch``: written tables in the cluster's shared folder, to cut lineage
  without depending on any single executor.
* ``keyed``: a stable row key even where ``doc_id`` is null or repeated.
* ``IdFilter``: a Bloom filter over ids whose size never exceeds a fixed bound.
* ``components``: distributed connected components.
* batch kernels over Arrow string columns.
"""

from __future__ import annotations

import ctypes
import functools
import inspect
import itertools
import math
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Upper bound of a broadcast Bloom filter, in bits (8 MB).
BLOOM_MAX_BITS = 1 << 26
#: Tasks that fill parts of a filter at once, at most.
FILTER_TASKS = 512
#: A row key that earlier steps have put beside the columns of the documents.
RID = "__gridlake_rid"
#: Text bytes that a kernel works on at once.
CHUNK_BYTES = 1 << 18


def spare() -> None:
    """Gives freed memory back, which a Python worker would hold while it waits for tasks."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def lean(run: Callable) -> Callable:
    """A kernel over batches, or over the table of a group, that holds no freed memory afterwards."""
    if inspect.isgeneratorfunction(run):

        @functools.wraps(run)
        def kernel(batches):
            try:
                yield from run(batches)
            finally:
                spare()

    else:

        @functools.wraps(run)
        def kernel(table):
            try:
                return run(table)
            finally:
                spare()

    return kernel


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers that don't see the driver's path."""
    sc = spark.sparkContext
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    if root in (sc._jvm.System.getenv("PYTHONPATH") or "").split(":") or getattr(sc, "_gridlake_shipped", False):
        return
    fd, name = tempfile.mkstemp(prefix="gridlake-", suffix=".zip")
    os.close(fd)
    with zipfile.ZipFile(name, "w") as z:
        for folder, _, files in os.walk(os.path.join(root, "gridlake")):
            for f in files:
                if f.endswith(".py"):
                    path = os.path.join(folder, f)
                    z.write(path, os.path.relpath(path, root))
    sc.addPyFile(name)
    sc._gridlake_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; one is set only where it is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="gridlake-checkpoints-"))
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


def _file(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


#: Paths of results that were handed out; they are deleted when the application ends.
_handed: list[str] = []


def handed() -> int:
    """A mark for ``release``."""
    return len(_handed)


def release(spark: SparkSession, mark: int) -> None:
    """Deletes results handed out since the mark, once nothing reads them any more."""
    for path in _handed[mark:]:
        fs, where = _file(spark, path)
        fs.delete(where, True)
    del _handed[mark:]


class Scratch:
    """Tables written for one run of an operator.

    ``save`` writes now and reads back, so later jobs start from files that every
    executor can reach; a name can be used again.  Leaving the ``with`` block deletes all but ``keep``.
    """

    def __init__(self, spark: SparkSession, name: str):
        ship(spark)
        self.spark, self.root = spark, f"{shared_dir(spark)}/gridlake-{name}-{uuid.uuid4().hex}"
        #: Names and paths of what may be deleted.
        self.made: list[tuple[str, str]] = []
        self.count = 0

    def __enter__(self) -> Scratch:
        return self

    def save(self, df: DataFrame, name: str, keep: bool = False, partition_by: str | None = None) -> DataFrame:
        path = f"{self.root}/{self.count}-{name}"
        self.count += 1
        writer = df.write.mode("overwrite").option("compression", "zstd")
        (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)
        if keep:
            fs, where = _file(self.spark, path)
            fs.deleteOnExit(where)
            _handed.append(path)
        else:
            self.made.append((name, path))
        return self.spark.read.schema(df.schema).parquet(path)

    def keep(self, df: DataFrame, name: str = "result") -> DataFrame:
        return self.save(df, name, keep=True)

    def drop(self, *names: str) -> None:
        for name, path in [m for m in self.made if not names or m[0] in names]:
            fs, where = _file(self.spark, path)
            fs.delete(where, True)
            self.made.remove((name, path))

    def __exit__(self, *_) -> None:
        self.drop()


def unique_ids(docs: DataFrame) -> bool:
    return not docs.groupBy("doc_id").count().where("count > 1 OR doc_id IS NULL").limit(1).count()


def numbered(s: Scratch, docs: DataFrame) -> DataFrame:
    """``docs`` with all its columns and the row key that ``keyed`` would give, as RID."""
    if unique_ids(docs):
        return docs.withColumn(RID, F.col("doc_id").cast("long"))
    return s.keep(docs.withColumn(RID, F.monotonically_increasing_id()), "numbered")


def keyed(s: Scratch, docs: DataFrame) -> DataFrame:
    """``rid, doc_id, text`` of ``docs``, null texts as empty.

    ``rid`` is ``doc_id`` where that is unique and not null.  Otherwise the rows are
    written once with a running number, so that repeated rows stay separate documents.
    """
    given = [F.col(RID).alias("rid")] if RID in docs.columns else []
    docs = docs.select(*given, F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    if given:
        return docs
    if unique_ids(docs):
        return docs.select(F.col("doc_id").alias("rid"), "doc_id", "text")
    return s.save(docs.select(F.monotonically_increasing_id().alias("rid"), "doc_id", "text"), "keyed")


def mixed(x: np.ndarray) -> np.ndarray:
    """The finaliser of a public 64-bit mixer, on uint64 arrays."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class IdFilter:
    """A Bloom filter over long ids with at most BLOOM_MAX_BITS bits.

    It has no false negatives.  Beyond the bound its false positives grow, which only
    lets more rows through to the exact join behind it.
    """

    def __init__(self, bits: np.ndarray, log2: int, hashes: int):
        self.bits, self.log2, self.hashes = bits, log2, hashes

    @staticmethod
    def slots(ids: np.ndarray, log2: int, hashes: int) -> Iterator[np.ndarray]:
        h = ids.astype(np.int64).view(np.uint64)
        for k in range(hashes):
            yield mixed(h + np.uint64((k + 1) * 0x9E3779B97F4A7C15 & (2**64 - 1))) >> np.uint64(64 - log2)

    @classmethod
    def of(cls, ids: DataFrame, column: str, count: int) -> IdFilter:
        """Built from a column of ids; ``count`` only sizes it.

        Every task fills a filter of its own; where there are many, slices of them are
        put together by other tasks, so the driver gets one filter's worth of bytes.
        """
        log2 = min(int(math.log2(BLOOM_MAX_BITS)), max(12, math.ceil(math.log2(max(1, count) * 12))))
        hashes = max(1, min(4, round(0.7 * (1 << log2) / max(1, count))))  # fewer where bits are scarce

        size = 1 << log2 >> 3
        slices = max(1, size >> 17)

        @lean
        def build(batches):
            bits = np.zeros(size, np.uint8)
            for b in batches:
                got = b.column(0).to_numpy(zero_copy_only=False)
                for s in cls.slots(got, log2, hashes):
                    np.bitwise_or.at(bits, (s >> np.uint64(3)).astype(np.int64), (1 << (s & np.uint64(7))).astype(np.uint8))
            for k, part in enumerate(np.split(bits, slices)):
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([part.tobytes()], pa.binary())], ["slice", "bits"])

        @lean
        def together(t: pa.Table) -> pa.Table:
            total = np.zeros(size // slices, np.uint8)
            for x in t.column("bits").to_pylist():
                total |= np.frombuffer(x, np.uint8)
            return pa.table({"slice": t.column("slice").slice(0, 1), "bits": pa.array([total.tobytes()], pa.binary())})

        few = ids.select(F.col(column).cast("long")).where(F.col(column).isNotNull()).coalesce(FILTER_TASKS)
        merged = few.mapInArrow(build, "slice int, bits binary").groupBy("slice").applyInArrow(together, "slice int, bits binary")
        total = np.zeros(size, np.uint8)
        for k, bits in merged.collect():
            total[k * (size // slices) : (k + 1) * (size // slices)] = np.frombuffer(bits, np.uint8)
        return cls(total, log2, hashes)

    def test(self, ids: np.ndarray) -> np.ndarray:
        ok = np.ones(len(ids), bool)
        for s in self.slots(ids, self.log2, self.hashes):
            ok &= (self.bits[(s >> np.uint64(3)).astype(np.int64)] >> (s & np.uint64(7)).astype(np.uint8)) & 1 == 1
        return ok


def components(s: Scratch, edges: DataFrame, rounds: int = 60) -> DataFrame:
    """Connected components of undirected ``edges (a, b)``: rows ``(rid, comp)``, comp the smallest id.

    Alternates "all larger neighbours point to my smallest neighbour" and "all smaller
    ones do"; both steps are one aggregate and one join, and the number of rounds is
    logarithmic.  Nothing is collected but a count and a checksum.  Labels that are still
    moving after ``rounds`` rounds are an error, never a result.
    """
    e = s.save(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "cc-0")
    last = None
    for k in itertools.count(1):
        if k > rounds:
            raise RuntimeError(f"components did not settle in {rounds} rounds")
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        low2 = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low2, "u").select(F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("p")).select("p.u", "p.v").where("u <> v").distinct()
        new = s.save(small, f"cc-{k}")
        mark = new.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        s.drop(f"cc-{k - 1}")
        e = new
        if tuple(mark) == last:
            break
        last = tuple(mark)
    tails = e.select(F.col("u").alias("rid"), F.col("v").alias("comp"))
    return tails.union(e.select(F.col("v").alias("rid"), F.col("v").alias("comp")).distinct())


def column_of(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def text_spans(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column and its offsets (len + 1)."""
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    _, offs, data = col.buffers()
    o = np.frombuffer(offs, np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    d = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return d, o


def doc_chunks(offsets: np.ndarray, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows with about ``limit`` bytes of text; a longer text is a range of its own."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1)
        yield lo, min(hi, n)
        lo = min(hi, n)
