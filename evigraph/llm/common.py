"""What the operators share: inputs, shared scratch space, global order by id ranges."""

from __future__ import annotations

import tempfile
import uuid
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


ARROW_ROWS = 1_000


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The documents. Whole texts go through Arrow, so its batches are kept at ARROW_ROWS rows at most (a runtime setting): a batch of
    10000 texts costs an executor some hundred MB on both sides of the pipe."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= ARROW_ROWS:
        spark.conf.set(name, str(ARROW_ROWS))
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def free(df: DataFrame, name: str) -> str:
    """A column name that the table doesn't have in any case of letters."""
    own = {c.lower() for c in df.columns}
    while name.lower() in own:
        name += "_"
    return name


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder under spark.checkpoint.dir, which the driver and all executors share.

    Only a session on one machine (tests) may have none: a temporary folder is made and set there.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="evigraph-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def saved(df: DataFrame, name: str, light: bool = False) -> DataFrame:
    """Cut the lineage by a table in the shared folder; a lost executor loses nothing of it.

    A light table (keys and numbers only) is written in one file a core at most, as many small files cost more than they hold.
    """
    spark = df.sparkSession
    path = scratch(spark, name)
    (df.coalesce(max(4, spark.sparkContext.defaultParallelism)) if light else df).write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def forget(*tables: DataFrame) -> None:
    """Delete saved tables that nothing will read again."""
    for df in tables:
        context = df.sparkSession.sparkContext
        path = context._jvm.org.apache.hadoop.fs.Path(df._scratch)
        path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def long_array(values: list[int]) -> Column:
    """A literal array of BIGINT, parsed once by constant folding."""
    return F.from_json(F.lit("[" + ",".join(map(str, values)) + "]"), "array<bigint>")


FAN = 32


def range_cuts(df: DataFrame, column: str) -> list[int]:
    """At most FAN*FAN - 1 ascending cut points that deal the column's rows into even ranges.

    The number of cuts is fixed, so what reaches the driver doesn't grow with the table.
    """
    n = FAN * FAN
    got = df.agg(F.percentile_approx(column, [i / n for i in range(1, n)], 20 * n).alias("q")).first()
    cuts = list(got["q"] or [0])
    return cuts + [cuts[-1]] * (n - 1 - len(cuts))


def range_of(value: Column, cuts: list[int]) -> Column:
    """Number of the range that a value lies in (null: 0), by two short scans of the cut points."""
    outer = long_array([cuts[i * FAN - 1] for i in range(1, FAN)])
    inner = F.from_json(
        F.lit(str([[int(x) for x in cuts[i * FAN : i * FAN + FAN - 1]] for i in range(FAN)])), "array<array<bigint>>"
    )
    coarse = F.size(F.filter(outer, lambda c: c <= value))
    pick = F.transform(F.array(coarse), lambda k: k * FAN + F.size(F.filter(F.element_at(inner, k + 1), lambda c: c <= value)))
    return F.when(value.isNull(), F.lit(0)).otherwise(F.element_at(pick, 1)).cast("int")


def let(value: Column, body) -> Column:
    """Bind a value once inside an expression."""
    return F.element_at(F.transform(F.array(value), body), 1)


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)
