"""Design matrices of the experiment workloads from the given tables.

Features are standardised by constants written here, not by the data, so that
every method sees the same matrix.  Logistic, ReLU and probit rows are -y x;
lp regression appends the target as a last column (the solution's last entry is -1).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from .tables import table, typed


def fold(rows: DataFrame, problem: str) -> DataFrame:
    """(row_id, vec) from (row_id, x, y, target)."""
    if problem in ("lp", "l1"):
        return rows.select("row_id", F.concat("x", F.array("target")).alias("vec"))
    return rows.select("row_id", F.transform("x", lambda v: -F.col("y") * v).alias("vec"))


def w1_lineitem(spark: SparkSession, sf: str, problem: str = "logistic") -> DataFrame:
    """Line items; label: returned. Near-uniform leverage: the control."""
    li = typed(spark, sf, "lineitem").withColumn("row_id", F.xxhash64(*[F.col(c) for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")]).bitwiseAND((1 << 61) - 1))
    part = table(spark, sf, "part").select(F.col("p_partkey").alias("l_partkey"), "p_size")
    j = li.join(part, "l_partkey", "left")
    x: list[Column] = [F.lit(1.0).cast("double"), F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10, (F.col("l_linestatus") == "O").cast("double"), F.coalesce(F.col("p_size"), F.lit(25)) / 50.0]
    if problem != "l1" and problem != "lp":
        x.append(F.col("l_extendedprice") / 1e5)
    return fold(j.select("row_id", F.array(*x).alias("x"), F.when(F.col("l_returnflag") == "R", 1.0).otherwise(-1.0).alias("y"), (F.col("l_extendedprice") / 1e5).alias("target")), problem)


def w2_documents(spark: SparkSession, sf: str, problem: str = "logistic", labelled: bool = True, buckets: int = 8) -> DataFrame:
    """Documents; label: quality (or, without labels, language en). Skewed leverage."""
    d = table(spark, sf, "documents")
    words = F.size(F.split("text", r"\s+")).cast("double")
    lines = F.size(F.split("text", "\n")).cast("double")
    chars = F.length("text").cast("double")
    x = [F.lit(1.0).cast("double"), F.log1p(words) / 10, F.log1p(lines) / 5, F.length(F.regexp_replace("text", r"[^0-9]", "")) / (chars + 1) * 20, F.length(F.regexp_replace("text", r"[^!-/:-@|]", "")) / (chars + 1) * 5, F.length(F.regexp_replace("text", r"[^A-Z]", "")) / (chars + 1) * 5]
    base = d.select(F.col("doc_id").alias("row_id"), F.array(*x).alias("x"), (chars / 1e3).alias("target"), "lang")
    if labelled:
        lab = table(spark, sf, "labels").select(F.col("doc_id").alias("row_id"), "quality")
        rows = base.join(lab, "row_id").withColumn("y", F.when(F.col("quality") == 1, 1.0).otherwise(-1.0))
    else:
        rows = base.withColumn("y", F.when(F.col("lang") == "en", 1.0).otherwise(-1.0))
    return fold(rows, problem)


def w3_events(spark: SparkSession, sf: str, problem: str = "logistic") -> DataFrame:
    """Events; label: error. The most skewed leverage."""
    e = typed(spark, sf, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-20, -1)
    k = F.get_json_object("props", "$.k").cast("double")
    past = F.coalesce(F.sum("value").over(w), F.lit(0.0))
    rolled = e.withColumn("past", past).withColumn("k", F.coalesce(k, F.lit(0.0)))
    x = [F.lit(1.0).cast("double"), F.hour("ts") / 24.0, F.col("k") / 100, F.col("past") / 1000]
    if problem in ("l1", "lp"):
        x += [(F.col("event_type") == t).cast("double") for t in ("click", "purchase")]
    else:
        x += [F.col("value") / 100, F.col("value") * F.col("value") / 1e5]
    return fold(rolled.select(F.col("event_id").alias("row_id"), F.array(*x).alias("x"), F.when(F.col("event_type") == "error", 1.0).otherwise(-1.0).alias("y"), (F.col("value") / 100).alias("target")), problem)


def w13_embeddings(spark: SparkSession, sf: str, problem: str = "logistic") -> DataFrame:
    e = table(spark, sf, "embeddings")
    rows = e.select(F.col("vec_id").alias("row_id"), F.transform("embedding", lambda v: v.cast("double")).alias("x"), F.when(F.col("label") == 0, 1.0).otherwise(-1.0).alias("y"), F.col("label").cast("double").alias("target"))
    return fold(rows, problem)


def w15_pages(spark: SparkSession, sf: str) -> DataFrame:
    """(row_id, vec) of url depth, html length, tag counts."""
    p = table(spark, sf, "pages")
    tags = [F.regexp_count("html", F.lit(f"<{t}[ >]")).cast("double") for t in ("p", "a", "li", "div")]
    return p.select(F.col("page_id").alias("row_id"), F.array(F.lit(1.0).cast("double"), F.regexp_count("url", F.lit("/")).cast("double"), F.length("html") / 1000.0, *tags).alias("vec"))


def w15_conversations(spark: SparkSession, sf: str) -> DataFrame:
    """(row_id, vec) of characters by role and number of turns."""
    c = table(spark, sf, "conversations")
    size = lambda r: F.coalesce(F.sum(F.when(F.col("role") == r, F.length("text"))), F.lit(0)).cast("double")
    return c.groupBy(F.col("conv_id").alias("row_id")).agg(F.array(F.count("*").cast("double"), size("system"), size("user"), size("assistant")).alias("vec"))


def width(rows: DataFrame) -> int:
    """Columns of a design matrix, from its first row."""
    return len(rows.select("vec").first()[0])
