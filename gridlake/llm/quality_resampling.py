"""Quality classifier by importance resampling.

Two generative bag models over hashed word unigrams and bigrams: one of the target text
(documents labelled good), one of the raw text (all documents).  A document's weight is
the mean log ratio of the two over its n-grams, shrunk for short texts; Gumbel noise is
added and the k largest keys are taken, which samples k documents without replacement
in proportion to their weights.  k is the number of documents whose weight reaches the
threshold that parts the labelled sample best.

Defined results: a null or empty text has no n-grams and weight 0; documents whose id is
null never count as labelled; ties of keys go to the smaller row key; without labels of
both kinds every document is taken; rows that share an id are documents of their own, and
of those with labels the first 2 * LABELLED by row key fit the threshold; an empty table
gives no rows; other columns are not read, whatever their names; texts are worked on whole,
a longer one than a chunk by itself.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridlake.llm.common import Scratch, doc_chunks, keyed, mixed, text_spans
from gridlake.llm.textkernels import word_hashes

BUCKETS = 1 << 16
#: Labelled rows that the target model and the threshold are fitted on, at most.
LABELLED = 20_000
#: Added to the n-gram count under the weight, so that short texts weigh near 0.
SHRINK = 10
#: Weight that one unit of Gumbel noise is worth.
TEMPERATURE = 0.004
#: How many rejected bad documents a rejected good one counts for in the threshold.
GOOD_COST = 8.0
SEED = 42


def ngrams(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bucket and text number of every unigram and bigram."""
    words, bounds = word_hashes(data, offsets)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(bounds))
    pair = mixed(words[:-1] * np.uint64(3) + words[1:])
    same = doc[:-1] == doc[1:]
    grams = np.concatenate((words, pair[same])) & np.uint64(BUCKETS - 1)
    return grams.astype(np.int64), np.concatenate((doc, doc[:-1][same]))


def labelled_sample(labels: DataFrame, most: int = LABELLED) -> dict[int, int]:
    """Quality of at most ``most`` labelled documents, picked by a hash of their id."""
    good = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").select(F.col("doc_id").cast("long"), F.col("quality").cast("int"))
    return {r.doc_id: r.quality for r in good.orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(most).collect()}


def gram_counts(rows: DataFrame, sample: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """N-gram counts by bucket over all texts and over the target texts."""
    good = pa.array(sorted(k for k, q in sample.items() if q == 1), pa.int64())

    def count(batches):
        raw, target = np.zeros(BUCKETS, np.int64), np.zeros(BUCKETS, np.int64)
        for batch in batches:
            known = pc.is_in(batch.column(0), value_set=good, skip_nulls=True).to_numpy(zero_copy_only=False)
            data, offs = text_spans(batch.column(1))
            for lo, hi in doc_chunks(offs):
                grams, doc = ngrams(data, offs[lo : hi + 1])
                raw += np.bincount(grams, minlength=BUCKETS)
                target += np.bincount(grams[known[lo:hi][doc]], minlength=BUCKETS)
        has = np.flatnonzero(raw)
        yield pa.RecordBatch.from_arrays([pa.array(has), pa.array(raw[has]), pa.array(target[has])], ["bucket", "raw", "target"])

    raw, target = np.zeros(BUCKETS), np.zeros(BUCKETS)
    parts = rows.select("doc_id", "text").mapInArrow(count, "bucket long, raw long, target long")
    for b, r, t in parts.groupBy("bucket").agg(F.sum("raw"), F.sum("target")).collect():  # BUCKETS rows at most
        raw[b], target[b] = r, t
    return raw, target


def log_ratio(raw: np.ndarray, target: np.ndarray) -> np.ndarray:
    """Log of target over raw probability of each bucket, both smoothed by one count."""
    return np.log((target + 1) / (target.sum() + BUCKETS)) - np.log((raw + 1) / (raw.sum() + BUCKETS))


def weights(rows: DataFrame, ratio: np.ndarray) -> DataFrame:
    """``rid, doc_id, n_grams, weight`` of every document."""

    def weigh(batches):
        for batch in batches:
            data, offs = text_spans(batch.column(2))
            n, total = np.zeros(batch.num_rows, np.int64), np.zeros(batch.num_rows)
            for lo, hi in doc_chunks(offs):
                grams, doc = ngrams(data, offs[lo : hi + 1])
                n[lo:hi] = np.bincount(doc, minlength=hi - lo)
                total[lo:hi] = np.bincount(doc, ratio[grams], minlength=hi - lo)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n), pa.array(total / (n + SHRINK))], ["rid", "doc_id", "n_grams", "weight"])

    return rows.mapInArrow(weigh, "rid long, doc_id long, n_grams long, weight double")


def threshold(scored: list[tuple[float, int]]) -> float | None:
    """The weight that parts good from bad with the least cost; None without both kinds."""
    if len({q for _, q in scored}) < 2:
        return None
    w = np.array([x for x, _ in scored])
    good = np.array([q == 1 for _, q in scored])
    order = np.argsort(w, kind="stable")
    w, good = w[order], good[order]
    # rejected: everything below position i
    lost = GOOD_COST * np.concatenate(([0], np.cumsum(good))) + np.concatenate((np.cumsum((~good)[::-1])[::-1], [0]))
    i = int(np.argmin(lost))
    return float(w[i - 1] + w[i]) / 2 if 0 < i < len(w) else float(w[0] - 1 if i == 0 else w[-1])


def top_k(rows: DataFrame, key: str, tie: str, k: int) -> DataFrame:
    """Boolean ``selected`` for the ``k`` largest keys, ties to the smaller ``tie``.

    The k-th key is found by histograms over ever narrower ranges, so neither a sort nor
    a single task sees all rows.
    """
    span = rows.agg(F.min(key), F.max(key), F.count("*")).first()
    if k >= span[2]:
        return rows.withColumn("selected", F.lit(True))
    if k <= 0:
        return rows.withColumn("selected", F.lit(False))
    lo, hi, above = float(span[0]), float(span[1]), 0
    while True:
        inside = rows.where((F.col(key) >= lo) & (F.col(key) <= hi))
        n = inside.count()
        width = (hi - lo) / 1024
        if n <= 4096 or width == 0 or lo + width == lo:
            break
        bins = dict(inside.groupBy(F.least(F.lit(1023), F.floor((F.col(key) - lo) / width)).alias("bin")).count().collect())
        for b in sorted(bins, reverse=True):
            if above + bins[b] >= k:
                edges = inside.where(F.least(F.lit(1023), F.floor((F.col(key) - lo) / width)) == b).agg(F.min(key), F.max(key)).first()
                break
            above += bins[b]
        if (lo, hi) == (float(edges[0]), float(edges[1])):
            break
        lo, hi = float(edges[0]), float(edges[1])
    if lo < hi or n <= 4096:
        last = sorted(inside.select(key, tie).collect(), key=lambda r: (-r[0], r[1]))[k - above - 1]
        at, first = last[0], last[1]
    else:  # very many equal keys: the ties are parted by the same search
        at = lo
        ties = top_k(inside.withColumn("_minus", -F.col(tie).cast("double")), "_minus", tie, k - above)
        first = ties.where("selected").agg(F.max(tie)).first()[0]
    return rows.withColumn("selected", (F.col(key) > at) | ((F.col(key) == at) & (F.col(tie) <= first)))


def resample(s: Scratch, docs: DataFrame, labels: DataFrame, seed: int = SEED) -> DataFrame:
    """``rid, doc_id, n_grams, weight, gumbel_key, selected`` of every document."""
    rows = keyed(s, docs)
    sample = labelled_sample(labels)
    raw, target = gram_counts(rows, sample)
    scored = weights(rows, log_ratio(raw, target))
    bits = F.shiftrightunsigned(F.xxhash64("rid", F.lit(seed)), 11).cast("double")
    gumbel = -F.log(-F.log((bits + 0.5) / float(1 << 53)))
    scored = s.keep(scored.withColumn("gumbel_key", F.col("weight") / TEMPERATURE + gumbel), "scored")
    known = s.spark.createDataFrame(list(sample.items()) or [(None, None)], "doc_id long, quality int")
    pairs = [(r.weight, r.quality) for r in scored.join(F.broadcast(known), "doc_id").orderBy("rid").select("weight", "quality").limit(2 * LABELLED).collect()]
    at = threshold(pairs)
    if at is None:
        return scored.withColumn("selected", F.lit(True))
    return top_k(scored, "gumbel_key", "rid", scored.where(F.col("weight") >= at).count())
