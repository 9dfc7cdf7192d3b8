"""Registered SQL, keys of chunks and streams that get late rows."""

from datetime import datetime

import pytest
from pyspark.sql import functions as F

from gridlake.plans import predicate as pr
from gridlake.plans.catalog import Catalog
from gridlake.queries.registry import Context
from gridlake.streaming import ops

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def known(spark):
    out = Catalog(spark)
    out.register("g3", Context(spark, SF).grid("g3"))
    return out


def test_filters_reach_the_leaf(spark, known):
    text = "SELECT SUM(n_lines) AS n FROM g3 WHERE (qty <= 10 OR disc IN (0.01, 0.02)) AND ship_month > TIMESTAMP_NTZ '1997-01-01' AND price_sum > 5"
    tree = known.predicates(text)["g3"]
    atoms = []

    def walk(node):
        if isinstance(node, pr.And | pr.Or):
            for p in node.parts:
                walk(p)
        elif isinstance(node, pr.Atom):
            atoms.append((node.axis, node.op, node.value))

    walk(tree)
    assert {("qty", "<=", 10.0), ("disc", "=", 0.01), ("disc", "=", 0.02), ("ship_month", ">", datetime(1997, 1, 1))} <= set(atoms)
    got = known.sql(text)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "chunk_key" in plan.split("PartitionFilters: [")[1].split("]")[0]
    assert got.first().n == known.grids["g3"].rows().where("(qty <= 10 OR disc IN (0.01, 0.02)) AND ship_month > TIMESTAMP_NTZ '1997-01-01' AND price_sum > 5").agg(F.sum("n_lines")).first()[0]


def test_negated_conditions(known):
    tree = known.predicates("SELECT * FROM g3 WHERE NOT (qty > 20 OR disc NOT IN (0.03))")["g3"]
    assert pr.clauses_of(tree)[0].ranges["qty"][1] == (0, 20.0, 1)


def test_no_filter_no_predicate(known):
    assert [c.ranges for c in pr.clauses_of(known.predicates("SELECT COUNT(*) FROM g3")["g3"])] == [{}]


def test_negative_ids(spark, tmp_path):
    ids = [-(2**63), -5, -4, -3, 0, 2, 7, 2**63 - 1]
    spark.createDataFrame([(k, [1.0, 2.0]) for k in ids], "vec_id long, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))
    grid = Context(spark, str(tmp_path)).grid("gv")
    for low, high in ((-5, 2), (-4, 7), (0, 0), (-3, -3)):
        got = {r.vec_id for r in grid.scan(["vec_id"], f"vec_id >= {low} AND vec_id <= {high}").collect()}
        assert got == {k for k in ids if low <= k <= high}


def files(spark, tmp_path, batches):
    folder = str(tmp_path / "events")
    for k, rows in enumerate(batches):
        spark.createDataFrame([(k * 100 + i, datetime.fromisoformat(t), 1, "click", v, "{}") for i, (t, v) in enumerate(rows)], ops.SCHEMA).coalesce(1).write.mode("append").parquet(folder)
    return spark.readStream.schema(ops.SCHEMA).option("maxFilesPerTrigger", 1).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def test_update_keeps_the_last_state(spark, tmp_path):
    stream = files(spark, tmp_path, [[("2024-01-01 10:00:00", 3.0)], [("2024-01-01 11:00:00", 9.0), ("2024-01-02 01:00:00", 1.0)]])
    got = {r.chunk: (r.value_lo, r.value_hi) for r in ops.drained(ops.state_bounds(stream), "update", ("chunk",)).collect()}
    assert got == {"2024-01-01": (3.0, 9.0), "2024-01-02": (1.0, 1.0)}


def test_late_rows(spark, tmp_path):
    """Appending drops what comes behind the watermark, complete output counts it."""
    batches = [[("2024-01-02 10:00:00", 1.0)], [("2024-01-03 10:00:00", 1.0)], [("2024-01-01 10:00:00", 1.0), ("2024-01-05 10:00:00", 1.0)], [("2024-01-09 10:00:00", 1.0)]]
    appended = {str(r.start) for r in ops.drained(ops.tumbling(files(spark, tmp_path, batches))).collect()}
    whole = {str(r.start) for r in ops.drained(ops.tumbling(files(spark, tmp_path / "again", batches)), "complete").collect()}
    assert "2024-01-01 10:00:00" in whole and "2024-01-01 10:00:00" not in appended and "2024-01-02 10:00:00" in appended
