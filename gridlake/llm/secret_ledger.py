"""Secret scans with an incremental blob ledger.

Every version of every path is content-addressed: its blob id is the SHA-256 of the
text.  Rules come in packs, each with a version of its own.  The ledger holds what each
(blob, rule version) pair gave, also where it gave nothing.  A run finds the pairs that are
not in the ledger, scans one representative of each such blob by the packs it lacks, adds
the findings to the ledger and joins them back to all paths that ever held the blob.

Defined results: a null text is the empty blob; spans are code points, end exclusive;
repeated rows, rows without an id and copies share one scan and each get its findings; an
empty table gives no rows and adds nothing to the ledger; other columns are not read,
whatever their names; a text is scanned as a whole.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridlake.llm.bpe_dp import texts_of
from gridlake.llm.common import IdFilter, Scratch, keyed

# The base rules' patterns and kinds, in their order.
ASSIGN = r"""((?ai:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]{24,}"
BASE = ("assign", "access", "hex")
# What this method adds.
ADDED = {"jwt": r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", "private_key": r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----"}
KINDS = (*BASE, *ADDED)

_assign, _access, _hex = re.compile(ASSIGN), re.compile(ACCESS), re.compile(HEX)
_added = {k: re.compile(p) for k, p in ADDED.items()}
_hints = ("password", "passwd", "secret", "token", "api")

#: Rule versions and the kinds that each looks for.
PACKS = {"base-1": BASE, "added-1": tuple(ADDED)}
FINDINGS = "array<struct<start:int,kind:int,stop:int>>"
LEDGER = f"blob binary, rule_version string, findings {FINDINGS}"


def find(text: str, kinds: tuple[str, ...] = KINDS) -> list[tuple[int, int, int]]:
    """``(start, kind number, end)`` of all findings, sorted."""
    out = []
    if "assign" in kinds:
        low = text.lower()
        if any(h in low for h in _hints):
            out += [(m.start(), 0, m.end()) for m in _assign.finditer(text) if len(m[2]) >= 6]
    if "access" in kinds and "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in _access.finditer(text) if m.end() - m.start() >= 20]
    if "hex" in kinds:  # a maximal run of the class is the match, so its least length can be asked for at once
        out += [(m.start(), 2, m.end()) for m in _hex.finditer(text)]
    if "jwt" in kinds and "eyJ" in text:
        out += [(m.start(), 3, m.end()) for m in _added["jwt"].finditer(text)]
    if "private_key" in kinds and "-----BEGIN" in text:
        out += [(m.start(), 4, m.end()) for m in _added["private_key"].finditer(text)]
    return sorted(out)


def missing(s: Scratch, paths: DataFrame, ledger: DataFrame | None, versions: tuple[str, ...]) -> DataFrame:
    """``blob, rule_version, rid``: pairs that no ledger row answers, with one row of the blob."""
    blobs = paths.groupBy("blob").agg(F.min("rid").alias("rid"))
    pairs = blobs.withColumn("rule_version", F.explode(F.array(*map(F.lit, versions))))
    if ledger is not None:
        pairs = pairs.join(ledger.select("blob", "rule_version"), ["blob", "rule_version"], "left_anti")
    return s.save(pairs, "todo")


def named(findings: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(findings, lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"].cast("string"), x["stop"].cast("string"))), ",")


def ledger_scan(s: Scratch, docs: DataFrame, ledger: DataFrame | None = None, versions: tuple[str, ...] = tuple(PACKS)) -> tuple[DataFrame, DataFrame]:
    """Findings of every row of ``docs`` by the packs ``versions``, and the ledger's new rows.

    ``ledger`` has the columns of LEDGER; pass the union of what earlier calls returned.
    """
    rows = keyed(s, docs)
    paths = s.save(rows.select("rid", "doc_id", F.unhex(F.sha2("text", 256)).alias("blob")), "paths")
    todo = missing(s, paths, ledger, versions)
    wanted = [(v, PACKS[v], IdFilter.of(own, "rid", n)) for v in versions if (n := (own := todo.where(F.col("rule_version") == v)).count())]
    kind = pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("stop", pa.int32())]))

    def scan(batches):
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for version, kinds, some in wanted:
                part = batch.filter(pa.array(some.test(ids)))
                found = [[dict(zip(("start", "kind", "stop"), x, strict=True)) for x in find(t, kinds)] for t in texts_of(part.column(1))]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([version] * len(found), pa.string()), pa.array(found, kind)], ["rid", "rule_version", "findings"])

    fresh = todo.limit(0).select("blob", "rule_version", F.array().cast(FINDINGS).alias("findings"))
    if wanted:
        scanned = rows.select("rid", "text").mapInArrow(scan, f"rid long, rule_version string, findings {FINDINGS}")
        fresh = todo.join(scanned, ["rid", "rule_version"]).select("blob", "rule_version", "findings")
    fresh = s.keep(fresh, "ledger")
    known = fresh if ledger is None else fresh.unionByName(ledger.where(F.col("rule_version").isin(*versions)))
    # what all packs say of a blob, in order
    told = known.where(F.size("findings") > 0).groupBy("blob").agg(F.array_sort(F.flatten(F.collect_list("findings"))).alias("findings"))
    got = paths.join(told, "blob", "left").withColumn("findings", F.coalesce("findings", F.array().cast(FINDINGS)))
    # one parameter only: a second one, even with a default, would be the place in the array
    counts = [F.size(F.filter(F.col("findings")["kind"], (lambda k: lambda x: x == k)(k))).cast("long").alias(f"n_{name}") for k, name in enumerate(BASE)]
    base = F.sha2(named(F.filter("findings", lambda x: x["kind"] < len(BASE))), 256).alias("base_sha256")
    return s.keep(got.select("doc_id", *counts, base, named(F.col("findings")).alias("spans"), F.lower(F.hex("blob")).alias("blob")), "found"), fresh
