"""Licence scan: sparse TF-IDF cosine to templates, then inheritance from the nearest directory above.

Every line that speaks of a licence is a header unit, and so is the whole text of
a file named as a licence.  Equal units collapse first, so a header that stands in
a third of all files is scored once.  Terms weigh by inverse document frequency
over all units; a unit takes the template with the highest cosine at or above
the threshold.  A directory's licence comes from its licence files (by name, or
because licence lines make up at least half of the text); a file without a header
of its own takes that of the nearest directory above it, found by equal joins on
the directories' ancestors.

All on DataFrame functions: higher-order functions cut the texts, joins and
aggregates do the rest, and the directories, not the files, meet their ancestors.

Defined cases: null and empty texts have no header; a null path has no directory
and inherits nothing; equal scores go to the template first by name; repeated
rows keep their rows; other columns are left alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .common import checkpointed

#: Header and notice texts of common public licences.
TEMPLATES = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."),
    ("BSD-2-Clause", "Use of this source code is governed by a BSD 2-Clause license that can be found in the LICENSE file."),
    ("BSD-3-Clause", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related rights to this work (CC0 1.0)."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("Proprietary", "All rights reserved."),
]
TRIGGER = r"(?i)licen[cs]e|copyright|spdx|creative commons|all rights reserved|permission is hereby"
FILE_NAME = r"(?i)(^|/)(licen[cs]e|copying|notice|unlicense)[^/]*$"
TERM = r"[a-z0-9]+(?:[.\-][a-z0-9]+)*"
MIN_COSINE = 0.6
FILE_SHARE = 0.5


def terms(unit: Column) -> Column:
    """Lower-case alphanumeric terms, with inner dots and hyphens as in version numbers."""
    return F.regexp_extract_all(F.lower(unit), F.lit(TERM), F.lit(0))


def directory(path: Column) -> Column:
    return F.when(path.isNull(), F.lit(None)).when(F.instr(path, "/") > 0, F.regexp_replace(path, r"/[^/]*$", "")).otherwise("")


def scored_units(units: DataFrame, templates=TEMPLATES, min_cosine: float = MIN_COSINE) -> DataFrame:
    """Distinct units (unit, n) to (unit, license, score)."""
    spark = units.sparkSession
    patterns = spark.createDataFrame(templates, "license string, template string")
    word = lambda df, col: df.select("*", F.explode(terms(F.col(col))).alias("term"))
    tf = word(units, "unit").groupBy("unit", "n", "term").agg(F.count("*").alias("tf"))
    df = tf.groupBy("term").agg(F.sum("n").alias("df"))
    total = units.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    idf = lambda d: F.log((1.0 + total) / (1.0 + d)) + 1.0
    template_tf = word(patterns, "template").groupBy("license", "template", "term").agg(F.count("*").alias("tf"))
    base = template_tf.join(df, "term", "left").withColumn("w", F.col("tf") * idf(F.coalesce("df", F.lit(0))))
    base = base.join(base.groupBy("license", "template").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm")), ["license", "template"]).select("license", "template", "term", (F.col("w") / F.col("norm")).alias("wt"))
    weighed = tf.join(df, "term").withColumn("w", F.col("tf") * idf(F.col("df"))).select("unit", "term", "w")
    norms = weighed.groupBy("unit").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dots = weighed.join(base, "term").groupBy("unit", "license", "template").agg(F.sum(F.col("w") * F.col("wt")).alias("dot"))
    cosine = dots.join(norms, "unit").select("unit", "license", F.round(F.col("dot") / F.col("norm"), 4).alias("score"))
    best = cosine.groupBy("unit").agg(F.min(F.struct((-F.col("score")).alias("s"), "license")).alias("b"))
    return best.select("unit", F.col("b.license").alias("license"), (-F.col("b.s")).alias("score")).filter(F.col("score") >= min_cosine)


def scan(files: DataFrame, id_col: str = "doc_id", path_col: str = "path", text_col: str = "text", templates=TEMPLATES, min_cosine: float = MIN_COSINE) -> DataFrame:
    """Every file with license, score, how (header, inherited or none) and the directory it was inherited from."""
    named = files.select(F.col(id_col).alias("doc_id"), F.col(path_col).alias("path"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    is_file = F.coalesce(F.col("path").rlike(FILE_NAME), F.lit(False))
    lines = F.filter(F.transform(F.split("text", "\n"), lambda x: F.trim(x)), lambda x: x.rlike(TRIGGER))
    found = named.select("doc_id", "path", F.length("text").alias("size"), is_file.alias("by_name"), F.array_distinct(F.when(is_file, F.array_union(lines, F.array(F.trim("text")))).otherwise(lines)).alias("units"), F.aggregate(lines, F.lit(0), lambda a, x: a + F.length(x)).alias("spoken"))
    # The texts are read once; what follows works on the short rows.
    found = checkpointed(found.withColumn("row", F.monotonically_increasing_id()))
    # Rows without a header keep a place of their own in the join: no common key gathers them.
    flat = found.select("row", "doc_id", "path", (F.col("by_name") | (F.col("spoken") >= FILE_SHARE * F.col("size")) & (F.col("spoken") > 0)).alias("is_file"), F.explode_outer("units").alias("unit"))
    flat = flat.withColumn("unit", F.coalesce("unit", F.concat(F.lit("\u0000"), F.pmod("row", F.lit(100_003)).cast("string"))))
    units = found.select(F.explode("units").alias("unit")).groupBy("unit").agg(F.count("*").alias("n"))
    scores = scored_units(units, templates, min_cosine)
    own = flat.join(scores, "unit", "left").groupBy("row", "doc_id", "path", "is_file").agg(F.min(F.when(F.col("license").isNotNull(), F.struct((-F.col("score")).alias("s"), "license"))).alias("b"))
    own = own.select("doc_id", "path", "is_file", directory(F.col("path")).alias("dir"), F.col("b.license").alias("license"), (-F.col("b.s")).alias("score"))
    sources = own.filter("is_file and license is not null and dir is not null").groupBy("dir").agg(F.min(F.struct((-F.col("score")).alias("s"), "license", "path")).alias("b"))
    sources = sources.select(F.col("dir").alias("above"), F.col("b.license").alias("above_license"), (-F.col("b.s")).alias("above_score"))
    # Only directories meet their ancestors, one equal join each level.
    steps = F.split("dir", "/")
    ancestors = own.filter("dir is not null").select("dir").distinct().select("dir", F.explode(F.array_union(F.array(F.lit("")), F.transform(F.sequence(F.lit(1), F.size(steps)), lambda k: F.array_join(F.slice(steps, F.lit(1), k), "/")))).alias("above"))
    nearest = ancestors.join(sources, "above").groupBy("dir").agg(F.max(F.struct(F.length("above").alias("k"), "above", "above_license", "above_score")).alias("n"))
    out = own.join(nearest, "dir", "left")
    return out.select(
        "doc_id",
        "path",
        F.coalesce("license", "n.above_license").alias("license"),
        F.coalesce("score", "n.above_score").alias("score"),
        F.when(F.col("license").isNotNull(), "header").when(F.col("n").isNotNull(), "inherited").otherwise("none").alias("how"),
        F.when(F.col("license").isNull(), F.col("n.above")).alias("inherited_from"),
    )
