"""Document fingerprints: a canonical exact digest.

The canonical text has compatibility-normalised, case-folded characters and single
blanks for runs of white space, none at the ends.  Its 128-bit xxhash is the
fingerprint; documents with equal fingerprints are grouped and their canonical bytes
compared inside the bucket, so a group never rests on the hash alone.

Defined results: a null text is the empty text and has that text's fingerprint; equal
texts share a fingerprint; rows with equal ids, or none, are ordered by their text's hash (nulls
come first); for a single document the next one is itself; an empty table gives no rows;
other columns are not read, whatever their names; a text is worked on as a whole.
"""

from __future__ import annotations

import hashlib
import unicodedata

import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.llm.bpe_dp import texts_of
from gridlake.llm.common import IdFilter, Scratch, keyed

ROW = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
ENDS = ", pid int, first_text string, last_text string"
_TYPES = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64(), pa.int32(), pa.string(), pa.string())


def canonical(text: str) -> str:
    if text.isascii():
        return " ".join(text.lower().split())
    folded = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", text).casefold())
    return " ".join(folded.split())


def fingerprint(text: str) -> str:
    return xxhash.xxh3_128_hexdigest(canonical(text).encode("utf-8", "replace"))


def edited(text: str, following: str) -> str:
    """The text whose second half is replaced by the beginning of the following one."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def likeness(a: str, b: str) -> float:
    """Of exact digests: equal or not."""
    return float(a == b)


def compared(doc_id, text: str, own: str, following: str, next_print: str) -> tuple:
    new = edited(text, following)
    new_print = fingerprint(new)
    return doc_id, len(text), hashlib.sha256(new.encode("utf-8", "replace")).hexdigest(), own, new_print, likeness(own, new_print), likeness(own, next_print)


def _batch(rows: list[tuple], n: int = 10) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[]] * n
    names = [x.split()[0] for x in (ROW + ENDS).split(", ")][:n]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, _TYPES[:n], strict=True)], names)


def edit_report(s: Scratch, docs: DataFrame) -> DataFrame:
    """Every document against its edited text and the next document.

    One range shuffle puts neighbours side by side; the texts at the borders of
    partitions, one pair for each partition, are joined in a second small step.
    """
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    # rows of one id, or without one, are parted by their texts and places, so none is hot
    plain = plain.withColumns({"mark": F.xxhash64("text"), "place": F.monotonically_increasing_id()})
    dealt = plain.repartitionByRange("doc_id", "mark", "place").sortWithinPartitions("doc_id", "mark", "place").select("doc_id", "text")

    def walk(batches):
        pid, first, last = TaskContext.get().partitionId(), None, None
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), texts_of(batch.column(1)), strict=True):
                own = fingerprint(text)
                if last is None:
                    first = text
                else:
                    rows.append((*compared(*last, text, own), None, None, None))
                last = (doc, text, own)
            yield _batch(rows)
        if last is not None:
            yield _batch([(last[0], None, None, last[2], None, None, None, pid, first, last[1])])

    walked = s.save(dealt.mapInArrow(walk, ROW + ENDS), "walked")
    inner = walked.where("pid IS NULL").select(*[x.split()[0] for x in ROW.split(", ")])
    pids = sorted(r.pid for r in walked.where("pid IS NOT NULL").select("pid").collect())  # one for each partition
    after = dict(zip(pids, pids[1:] + pids[:1], strict=True))
    ends = walked.where("pid IS NOT NULL").select("doc_id", "pid", "first_text", "last_text", "fingerprint")
    order = s.spark.createDataFrame(list(after.items()) or [(0, 0)], "pid int, next_pid int")
    heads = ends.select(F.col("pid").alias("next_pid"), F.col("first_text").alias("following"))

    def stitch(batches):
        for batch in batches:
            rows = []
            for doc, text, own, following in zip(batch.column(0).to_pylist(), texts_of(batch.column(1)), batch.column(2).to_pylist(), texts_of(batch.column(3)), strict=True):
                rows.append(compared(doc, text, own, following, fingerprint(following)))
            yield _batch(rows, 7)

    border = ends.join(order, "pid").join(heads, "next_pid").select("doc_id", "last_text", "fingerprint", "following").mapInArrow(stitch, ROW)
    return s.keep(inner.unionByName(border))


def exact_groups(s: Scratch, docs: DataFrame) -> DataFrame:
    """``rid, doc_id, fingerprint, group_id, group_size``: groups of byte-equal canonical texts.

    Only members of buckets with several rows send their canonical text; the bucket is
    then grouped by those bytes, with partial aggregation before the shuffle, so a hot
    group costs one row for each task.
    """
    rows = keyed(s, docs)

    def prints(batches):
        for batch in batches:
            texts = [canonical(t).encode("utf-8", "replace") for t in texts_of(batch.column(2))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([xxhash.xxh3_128_hexdigest(t) for t in texts], pa.string()), pa.array([xxhash.xxh3_64_intdigest(t, seed=7) >> 1 for t in texts], pa.int64())], ["rid", "doc_id", "fingerprint", "second"])

    table = s.save(rows.mapInArrow(prints, "rid long, doc_id long, fingerprint string, second long"), "prints")
    several = table.groupBy("fingerprint").agg(F.count("*").alias("n")).where("n > 1")
    members = s.save(table.join(several, "fingerprint", "left_semi"), "members")
    some = IdFilter.of(members, "rid", members.count())

    def bodies(batches):
        for batch in batches:
            keep = some.test(batch.column(0).to_numpy(zero_copy_only=False))
            batch = batch.filter(pa.array(keep))
            texts = [canonical(t).encode("utf-8", "replace") for t in texts_of(batch.column(2))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([xxhash.xxh3_128_hexdigest(t) for t in texts], pa.string()), pa.array([xxhash.xxh3_64_intdigest(t, seed=7) >> 1 for t in texts], pa.int64()), pa.array(texts, pa.binary())], ["rid", "doc_id", "fingerprint", "second", "body"])

    sent = rows.mapInArrow(bodies, "rid long, doc_id long, fingerprint string, second long, body binary")
    equal = sent.groupBy("fingerprint", "second", "body").agg(F.min("doc_id").alias("group_id"), F.count("*").alias("group_size"))
    equal = s.save(equal.withColumn("exact", F.sha2("body", 256)).drop("body"), "equal")
    shared = equal.groupBy("fingerprint", "second").agg(F.count("*").alias("bodies")).where("bodies > 1").select("fingerprint", "second")
    if shared.limit(1).count():  # texts that share both hashes are told apart by their bytes
        shared = s.save(shared, "shared")
        apart = sent.join(F.broadcast(shared), ["fingerprint", "second"], "left_semi").select("rid", F.sha2("body", 256).alias("exact"))
        own = table.join(apart, "rid", "left")
        fits = (own["fingerprint"] == equal["fingerprint"]) & (own["second"] == equal["second"]) & (own["exact"].isNull() | (own["exact"] == equal["exact"]))
        joined = own.join(equal, fits, "left").select("rid", "doc_id", own["fingerprint"], F.coalesce("group_id", "doc_id").alias("group_id"), F.coalesce("group_size", F.lit(1)).alias("group_size"))
        return s.keep(joined, "groups")
    return s.keep(table.join(equal, ["fingerprint", "second"], "left").select("rid", "doc_id", "fingerprint", F.coalesce("group_id", "doc_id").alias("group_id"), F.coalesce("group_size", F.lit(1)).alias("group_size")), "groups")
