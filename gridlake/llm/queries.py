"""The operators' queries, one for each number, over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridlake.llm import bin_packing, bpe_dp, exact_digest, impact_topk, jaccard_join, pii_supervision, quality_resampling, secret_ledger, substring_dedup, url_filter
from gridlake.llm.common import Scratch


def tokenizer() -> str:
    """Where the public vocabulary lies; a parameter of the operators."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_importance_resampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "op1") as s:
        got = quality_resampling.resample(s, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
        return got.select("doc_id", "n_grams", "weight", "gumbel_key", "selected")


def op2_secret_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two visits to the table: the base rules first; then both packs, with the ledger that
    the first visit wrote, so no blob is scanned by the base rules again."""
    with Scratch(spark, "op2") as s:
        docs = table(spark, sf_dir, "documents")
        _, ledger = secret_ledger.ledger_scan(s, docs, versions=("base-1",))
        return secret_ledger.ledger_scan(s, docs, ledger)[0]


def op3_weak_supervision(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "op3") as s:
        return pii_supervision.report(s, table(spark, sf_dir, "documents"))


def op4_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "op4") as s:
        return substring_dedup.dedup(s, table(spark, sf_dir, "documents")).drop("rid", "kept")


def op5_impact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "op5") as s:
        return impact_topk.search(s, table(spark, sf_dir, "embeddings"))


def op6_bpe_dp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_dp.digest_documents(table(spark, sf_dir, "documents"), tokenizer())


def op7_exact_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "op7") as s:
        docs = table(spark, sf_dir, "documents")
        groups = exact_digest.exact_groups(s, docs).select("fingerprint", "group_id", "group_size").where("group_size > 1").distinct()
        report = exact_digest.edit_report(s, docs).join(groups, "fingerprint", "left")
        return report.withColumns({"group_id": F.coalesce("group_id", "doc_id"), "group_size": F.coalesce("group_size", F.lit(1))})


def op8_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bin_packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer())


def op9_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    with Scratch(spark, "op9") as s:
        return jaccard_join.join_components(s, table(spark, sf_dir, "documents")).drop("rid", "first_rid")


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages"))


def queries():
    return {f.__name__: f for f in (op1_importance_resampling, op2_secret_ledger, op3_weak_supervision, op4_suffix_array, op5_impact_topk, op6_bpe_dp, op7_exact_digest, op8_best_fit, op9_jaccard_join, op10_url_filter)}


_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: DuckDB SQL of the operators that it can express.
ORACLES = {
    "op5_impact_topk": """WITH v AS (SELECT row_number() OVER () AS r, vec_id, [CAST(floor(256 * CAST(x AS DOUBLE)) AS DOUBLE) for x in embedding] AS w FROM embeddings
WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len([x for x in embedding if x IS NULL OR NOT isfinite(x)]) = 0),
s AS (SELECT q.r, q.vec_id AS query_id, v.vec_id, CAST(list_dot_product(q.w, v.w) AS BIGINT) AS score FROM v q JOIN v ON q.r <> v.r WHERE q.vec_id % 50 = 0),
k AS (SELECT *, row_number() OVER (PARTITION BY r ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM k WHERE rank <= 5""",
    "op9_jaccard_join": f"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\\x20\\x09-\\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')] ELSE [array_to_string(ws[i : i + 4], ' ') for i in range(1, len(ws) - 3)] END) AS g FROM w),
t AS (SELECT doc_id, len(g) AS n, unnest(g) AS x FROM s),
p AS (SELECT a.doc_id AS d, b.doc_id AS e, any_value(a.n) AS n, any_value(b.n) AS m, COUNT(*) AS c FROM t a JOIN t b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT d, e FROM p WHERE 100 * c >= 80 * (n + m - c)),
u AS (SELECT d, e FROM l UNION ALL SELECT e, d FROM l),
r AS (SELECT doc_id AS d, doc_id AS root FROM s UNION SELECT u.e, r.root FROM r JOIN u ON u.d = r.d)
SELECT s.doc_id, CAST(len(s.g) AS BIGINT) AS n_shingles, MIN(r.root) AS component_id FROM s JOIN r ON r.d = s.doc_id GROUP BY s.doc_id, len(s.g)""",
}


def oracle_sql():
    return dict(ORACLES)
