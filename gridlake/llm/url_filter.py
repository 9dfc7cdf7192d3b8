"""URL filter: rules first, then word segmentation of the host and naive Bayes.

A unigram model of words splits concatenated host names by Viterbi search into their most
probable words.  A multinomial naive Bayes model over hashed tokens of segmented host and
path scores every URL that no rule decides.  It is trained on URLs that the rules decide
and on hosts that name a known unwanted trade.

Defined results: a URL that is null or has no ``://`` has empty host and path and is
scored by the prior; repeated rows give repeated results; an empty table gives no rows.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridlake.llm.common import ship

# The rules (host, path) and their verdicts.
RULES = {"org/": "allow", "example.org/es/": "block", "example.org/en/1": "block", "com/fr/": "allow", "com/de/": "block"}
# Words whose trade is unwanted; hosts that hold one are training examples.
UNWANTED = ("casino", "poker", "viagra", "porn", "xxx", "betting", "jackpot", "pills", "replica", "payday")
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Labelled URLs that the model is trained on, at most.
TRAINING = 20_000
BUCKETS = 1 << 15
LONGEST = 24


def parsed(pages: DataFrame) -> DataFrame:
    """``page_id, host, path`` of every page."""
    after = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    url = F.coalesce(F.col("url").cast("string"), F.lit(""))
    return pages.select(
        F.col("page_id").cast("long").alias("page_id"),
        F.translate(F.regexp_extract(url, after, 1), UPPER, LOWER).alias("host"),
        F.regexp_extract(url, after, 2).alias("path"),
    )


def rule_of(host: str, path: str) -> Column:
    """The longest rule that fits, else null."""
    out = F.lit(None).cast("string")
    for rule in sorted(RULES, key=len):  # the longest is tested first, so it is put on last
        name, _, rest = rule.partition("/")
        fits = ((F.col(host) == name) | F.col(host).endswith("." + name)) & F.col(path).startswith("/" + rest)
        out = F.when(fits, F.lit(rule)).otherwise(out)
    return out


def verdict_of(rule: str) -> Column:
    out = F.lit(None).cast("string")
    for name, verdict in RULES.items():
        out = F.when(F.col(rule) == name, F.lit(verdict)).otherwise(out)
    return out


def visible_text(html: str) -> Column:
    """A page's text without comments, scripts, styles, tags and entities."""
    text = F.coalesce(F.col(html).cast("string"), F.lit(""))
    text = F.regexp_replace(text, r"(?is)<!--.*?(?:-->|\z)|<(script|style)\b.*?(?:</\1|\z)", " ")
    return F.regexp_replace(text, r"<[^<>]*>|&#?\w+;", " ")


def word_counts(pages: DataFrame) -> tuple[dict[str, int], int]:
    """Counts in all pages' texts of every word that occurs in some host, and of all words."""
    words = pages.select(F.explode(F.regexp_extract_all(F.lower(visible_text("html")), F.lit("[a-z]+"), 0)).alias("word"))
    counted = words.groupBy("word").agg(F.count("*").alias("n"))
    # the windows at all places of the hosts' labels; their prefixes are all of the labels' parts
    windows = parsed(pages).select(F.explode(F.regexp_extract_all("host", F.lit(f"(?=([a-z]{{1,{LONGEST}}}))"), 1)).alias("w")).distinct()
    parts = windows.select(F.explode(F.expr("transform(sequence(1, length(w)), n -> substr(w, 1, n))")).alias("word")).distinct()
    found = counted.join(parts.withColumn("part", F.lit(True)), "word", "left")
    rows = found.groupBy(F.when(F.col("part"), F.col("word")).alias("word")).agg(F.sum("n").alias("n")).collect()
    return {r.word: r.n for r in rows if r.word is not None}, sum(r.n for r in rows)


class Segmenter:
    """Most probable split of a name into words of a unigram model.

    ``total`` counts all words of the texts, those that no name holds included.
    """

    def __init__(self, counts: dict[str, int], total: int | None = None):
        counts, seen = defaultdict(int, counts), sum(counts.values())
        for w in (*UNWANTED, "www", "blog", "news", "shop", "mail"):
            counts[w] += 1
        total = sum(counts.values()) + (0 if total is None else total - seen)
        self.logp = {w: math.log(n / total) for w, n in counts.items()}
        # an unknown string costs more the longer it is
        self.unknown = [0.0, *(math.log(10 / total) - n * math.log(10) for n in range(1, LONGEST + 1))]
        self.memo: dict[str, tuple[str, ...]] = {}

    def split(self, name: str) -> tuple[str, ...]:
        got = self.memo.get(name)
        if got is None:
            if len(self.memo) > 200_000:
                self.memo.clear()
            got = self.memo[name] = self._split(name)
        return got

    def _split(self, name: str) -> tuple[str, ...]:
        best, back = [0.0], [0]
        for end in range(1, len(name) + 1):
            choices = []
            for start in range(max(0, end - LONGEST), end):
                choices.append((best[start] + self.logp.get(name[start:end], self.unknown[end - start]), start))
            p, start = max(choices)
            best.append(p)
            back.append(start)
        out, end = [], len(name)
        while end:
            out.append(name[back[end] : end])
            end = back[end]
        return tuple(out[::-1])


_letters, _parts = re.compile(r"[a-z]+"), re.compile(r"[^\W_]+")


def tokens(host: str, path: str, segmenter: Segmenter) -> list[int]:
    """Buckets of the host's words and the path's parts, digits as one sign."""
    out = [f"h:{w}" for label in _letters.findall(host) for w in segmenter.split(label)]
    out += ["p:" + re.sub(r"\d+", "0", p.lower()) for p in _parts.findall(path)]
    return [zlib.crc32(t.encode()) % BUCKETS for t in out]


def judge(pages: DataFrame) -> DataFrame:
    """``page_id, host, path, rule, verdict, block_score`` of every page."""
    spark = pages.sparkSession
    ship(spark)
    counts, total = word_counts(pages)
    rows = parsed(pages).withColumn("rule", rule_of("host", "path")).withColumn("ruled", verdict_of("rule"))
    named = F.when(F.col("host").rlike("|".join(UNWANTED)), F.lit("block"))
    known = rows.withColumn("label", F.coalesce(named, F.col("ruled"))).where("label IS NOT NULL")
    known = known.orderBy(F.xxhash64("page_id", "host", "path"), "page_id", "host", "path").limit(TRAINING).select("host", "path", "label")

    def gather(batches):
        segmenter, seen = Segmenter(counts, total), np.zeros((2, BUCKETS + 1), np.int64)
        for batch in batches:
            for host, path, label in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                k = int(label == "block")
                seen[k, BUCKETS] += 1
                for t in tokens(host, path, segmenter):
                    seen[k, t] += 1
        has = np.flatnonzero(seen.any(0))
        yield pa.RecordBatch.from_arrays([pa.array(has), pa.array(seen[0, has]), pa.array(seen[1, has])], ["token", "allow", "block"])

    seen = np.zeros((2, BUCKETS + 1))
    for t, a, b in known.mapInArrow(gather, "token long, allow long, block long").groupBy("token").agg(F.sum("allow"), F.sum("block")).collect():
        seen[:, t] = a, b
    prior = math.log((seen[1, BUCKETS] + 1) / (seen[0, BUCKETS] + 1))
    likely = np.log((seen[:, :BUCKETS] + 1) / (seen[:, :BUCKETS].sum(1, keepdims=True) + BUCKETS))
    weight = likely[1] - likely[0]

    def score(batches):
        segmenter = Segmenter(counts, total)
        for batch in batches:
            out = [prior + float(sum(weight[t] for t in tokens(h, p, segmenter))) for h, p in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True)]
            verdict = [r or ("block" if x > 0 else "allow") for r, x in zip(batch.column(4).to_pylist(), out, strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], pa.array(verdict, pa.string()), pa.array(out, pa.float64())], ["page_id", "host", "path", "rule", "verdict", "block_score"])

    return rows.mapInArrow(score, "page_id long, host string, path string, rule string, verdict string, block_score double")
