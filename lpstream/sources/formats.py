"""Update logs in other file formats, sketches at rest, bucketed tables."""

from __future__ import annotations

import dataclasses
import json
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.params import SketchSpec

LOG = "row_id bigint, col_id int, delta double"


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder where the cluster shares files; a temporary one only where the session names none."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="ckpt-"))
    return f"{sc.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


def roundtrip(log: DataFrame) -> DataFrame:
    """Write and read the log in each format; one row a format: format, n, mass."""
    spark, out = log.sparkSession, None
    for kind in ("csv", "json", "orc"):
        path = scratch(spark, f"log-{kind}")
        log.write.format(kind).save(path)
        back = spark.read.schema(LOG).format(kind).load(path)
        one = back.agg(F.count("*").alias("n"), F.round(F.sum("delta"), 0).alias("mass")).select(F.lit(kind).alias("format"), "n", "mass")
        out = one if out is None else out.unionByName(one)
    return out


def save_sketch(sketch: DataFrame, spec: SketchSpec, path: str) -> None:
    """A sketch by repetition, with its specification as a JSON side file."""
    spark = sketch.sparkSession
    sketch.write.mode("overwrite").partitionBy("rep").parquet(f"{path}/cells")
    spark.createDataFrame([(json.dumps(dataclasses.asdict(spec)),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/spec")


def load_sketch(spark: SparkSession, path: str, spec: SketchSpec | None = None) -> tuple[DataFrame, SketchSpec]:
    """Cells and specification; a specification that is given must be the stored one."""
    found = SketchSpec(**json.loads(spark.read.text(f"{path}/spec").first()[0]))
    if spec is not None and spec != found:
        raise ValueError("sketches of different specifications can't be combined")
    cells = spark.read.parquet(f"{path}/cells")
    return cells.select(F.col("rep").cast("int").alias("rep"), "bucket", "col_id", "val"), found


def bucketed(log: DataFrame, name: str, buckets: int = 16) -> DataFrame:
    """The log as a table bucketed by row under a fresh name, so that sums by row need no shuffle."""
    spark = log.sparkSession
    name = f"{name}_{uuid.uuid4().hex[:12]}"
    log.write.bucketBy(buckets, "row_id").sortBy("row_id").option("path", scratch(spark, name)).saveAsTable(name)
    return spark.table(name)
