"""Tile store: dense row-major arrays in Parquet, one directory for each chunk.

``<root>/tiles``    chunk_key (partition), chunk, <span>_values, o_<axis> and n_<axis> for
                    every axis, one array column for each variable
``<root>/headers``  chunk_key, chunk, <axis>_values for every axis: what a chunk says of itself

A tile is bounded by the tile lengths given per axis, so a chunk of any size splits into
many tasks, and the fastest axis is left whole.  Chunk keys and tile origins are coarse
metadata; no value index is built.
"""

from __future__ import annotations

import tempfile
import uuid
from functools import reduce
from operator import mul

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridlake.model import Axis, GridSpec

#: Tiles in a file, about, and the column that says which file of its chunk a tile goes to.
FILE_TILES, PART = 256, "__gridlake_part"

_built: dict[tuple[str, str, str], GridSpec] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir, which all executors share; one of its own only
    where that is unset, as in local runs."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="gridlake-checkpoints-"))
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


def product(columns: list[Column]) -> Column:
    return reduce(mul, columns, F.lit(1))


def build_tiles(cells: DataFrame, axes: tuple[Axis, ...], variables: tuple[tuple[str, str], ...], tile_lens: dict[str, int]) -> tuple[DataFrame, DataFrame]:
    """Tiles and headers from sparse cells ``chunk_key, <span>, <axis>_ix..., variables``.

    Missing cells become NULL.  Every step is keyed by the chunk, and by the tile below it.
    """
    span = next(a for a in axes if a.spans)
    inner = [a for a in axes if not a.spans]
    heads = cells.groupBy("chunk_key").agg(F.array_sort(F.collect_set(span.name)).alias(f"{span.name}_values"))
    placed = cells.join(heads, "chunk_key").withColumn(span.ix, (F.array_position(f"{span.name}_values", F.col(span.name)) - 1).cast("int"))
    total = {a.name: F.lit(len(a.values)) for a in inner} | {span.name: F.size(f"{span.name}_values")}

    def step(a: Axis) -> Column:
        return F.lit(tile_lens[a.name]) if a.name in tile_lens else total[a.name]

    # one row for each tile that has a cell, or for each tile of the chunk: its size and origin
    skeleton = heads
    for a in axes:
        skeleton = skeleton.withColumn(f"o_{a.name}", F.explode(F.sequence(F.lit(0), total[a.name] - 1, step(a)))).withColumn(f"n_{a.name}", F.least(step(a), total[a.name] - F.col(f"o_{a.name}")))
    keys = ["chunk_key", *[f"o_{a.name}" for a in axes]]
    lin, stride = F.lit(0), F.lit(1)
    for a in reversed(axes):
        origin = F.col(a.ix) - F.col(a.ix) % step(a)
        lin = lin + (F.col(a.ix) - origin) * stride
        stride = stride * F.least(step(a), total[a.name] - origin)
        placed = placed.withColumn(f"o_{a.name}", origin)
    kind = f"struct<lin:int,{','.join(f'{n}:{t}' for n, t in variables)}>"
    cell = F.struct("lin", *[n for n, _ in variables]).cast(kind)
    filled = placed.withColumn("lin", lin).groupBy(*keys).agg(F.array_sort(F.collect_list(cell)).alias("cells"))
    sizes = [f"n_{a.name}" for a in axes]
    whole = skeleton.join(filled, keys, "left").withColumn("cells", F.coalesce("cells", F.array().cast(f"array<{kind}>")))

    def gap(size: Column) -> Column:
        return F.array_repeat(F.lit(None).cast(kind), size)

    # a tile's gaps are filled inside its array, each with as many nulls as it is long
    ahead = F.transform("cells", lambda c, i: F.concat(gap(c["lin"] - F.coalesce(F.get("cells", i - 1)["lin"], F.lit(-1)) - 1), F.array(c)))
    rest = gap((product([F.col(n) for n in sizes]) - 1 - F.coalesce(F.get("cells", F.size("cells") - 1)["lin"], F.lit(-1))).cast("int"))
    whole = whole.withColumn("row", F.concat(F.flatten(ahead), rest))
    tiles_of_chunk = product([F.ceil(total[a.name] / step(a)) for a in axes])
    tiles = whole.select(
        "chunk_key", F.col("chunk_key").alias("chunk"), f"{span.name}_values", *keys[1:], *sizes,
        *[F.col(f"row.{v}").alias(v) for v, _ in variables],
        F.pmod(F.xxhash64(*keys[1:]), F.ceil(tiles_of_chunk / FILE_TILES)).alias(PART),
    )
    headers = heads.select("chunk_key", F.col("chunk_key").alias("chunk"), *[F.col(f"{a.name}_values") if a.spans else F.lit(list(a.values)).alias(f"{a.name}_values") for a in axes])
    return tiles, headers


def write_grid(tiles: DataFrame, headers: DataFrame, path: str, partition: bool = True) -> None:
    """Tiles with a PART are written by as many tasks as their chunk has parts."""
    if PART in tiles.columns:
        tiles = tiles.repartition("chunk_key", PART).drop(PART)
    writer = tiles.write.mode("overwrite")
    (writer.partitionBy("chunk_key") if partition else writer).parquet(f"{path}/tiles")
    headers.write.mode("overwrite").parquet(f"{path}/headers")


def read_tiles(spark: SparkSession, path: str) -> DataFrame:
    """Tiles; the chunk key stays a string whatever it looks like."""
    before = spark.conf.get("spark.sql.sources.partitionColumnTypeInference.enabled")
    spark.conf.set("spark.sql.sources.partitionColumnTypeInference.enabled", "false")
    try:
        return spark.read.parquet(f"{path}/tiles")
    finally:
        spark.conf.set("spark.sql.sources.partitionColumnTypeInference.enabled", before)


def read_headers(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/headers")


def infer_grid(spark: SparkSession, name: str, path: str, spans: dict[str, bool], chunk_of: str = "", keyed: bool = True) -> GridSpec:
    """Axes, types and variables, from one chunk's header row and the tiles' footer.

    The schema is taken to be shared by all chunks; ``check_grid`` tests that.
    """
    heads = read_headers(spark, path)
    first = heads.orderBy("chunk_key").limit(1).first()
    axes = []
    for f in heads.schema.fields:
        if f.name.endswith("_values"):
            own = f.name.removesuffix("_values")
            spanning = spans.get(own, False)
            axes.append(Axis(own, spanning, f.dataType.elementType.simpleString(), () if spanning else tuple(first[f.name])))
    variables = tuple((f.name, f.dataType.elementType.simpleString()) for f in read_tiles(spark, path).schema.fields if f.dataType.typeName() == "array" and not f.name.endswith("_values"))
    return GridSpec(name, path, tuple(axes), variables, chunk_of, keyed)


def check_grid(spark: SparkSession, spec: GridSpec) -> int:
    """Chunks whose axes differ from the first chunk's."""
    odd = F.lit(False)
    for a in spec.inner:
        odd |= F.col(f"{a.name}_values") != F.lit(list(a.values))
    return read_headers(spark, spec.path).where(odd).count()


def cached(spark: SparkSession, sf_dir: str, name: str, build) -> GridSpec:
    """The grid ``name`` of these tables, ingested on first use by this application."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _built:
        path = f"{shared_dir(spark)}/gridlake-{name}-{uuid.uuid4().hex}"
        _built[key] = build(path)
    return _built[key]
