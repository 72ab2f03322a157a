"""Shared helpers of the training-data operators."""

from __future__ import annotations

import tempfile

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One input table; only Spark's own reader touches the path."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the session names.

    Where it names none, a temporary folder of a local session; executors of a
    cluster could not see one, so there it is an error.
    """
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="ckpt-"))
    return sc.getCheckpointDir()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def row_key(df: DataFrame) -> tuple[Column, Column]:
    """128 bits of a row's content: the same wherever and whenever the row is read again, and equal for equal rows."""
    parts = []
    for f in df.schema.fields:
        c = F.col("`" + f.name.replace("`", "``") + "`")
        if "map<" in f.dataType.simpleString() or "variant" in f.dataType.simpleString():
            c = F.to_json(F.struct(c.alias("v")))
        parts += [c.isNull(), c]
    return F.xxhash64(F.lit(1), *parts), F.xxhash64(F.lit(2), *parts)


def pick(df: DataFrame, wanted: DataFrame, columns: list[str]) -> DataFrame:
    """One row of `df` for each wanted key: its `columns`, with the further columns of `wanted`.

    `wanted` has (k0, k1, several, ...): the keys of `row_key`, and whether equal
    rows may exist.  Only those are gathered by key, after partial aggregation in
    each task; all others pass through the join.
    """
    extra = [c for c in wanted.columns if c not in ("k0", "k1", "several")]
    a, b = row_key(df)
    body = F.struct(*[F.col("`" + c.replace("`", "``") + "`") for c in columns])
    met = df.select(a.alias("k0"), b.alias("k1"), body.alias("body")).join(wanted, ["k0", "k1"])
    alone = met.filter(~F.col("several")).select("body", *extra)
    again = met.filter("several").groupBy("k0", "k1", *extra).agg(F.first("body").alias("body")).select("body", *extra)
    return alone.unionByName(again).select("body.*", *extra)


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: spreads small integers over the whole range."""
    x = x.astype(np.uint64, copy=True)
    with np.errstate(over="ignore"):
        x += np.uint64(0x9E3779B97F4A7C15)
        x ^= x >> np.uint64(30)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(31)
    return x


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenation of the index ranges [start, start+length)."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(lengths)
    return np.arange(total, dtype=np.int64) + np.repeat(starts - (ends - lengths), lengths)
