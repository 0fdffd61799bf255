"""Licence scan: sparse TF-IDF cosine to templates, then inheritance down the directory tree.

Headers are the sentences and lines of a text; licence files (by name) are also compared whole.
Terms weigh (1 + log tf) * idf, with idf over all files, for every term. A unit takes the template of the greatest
cosine, if that is `least` or more and two terms agree. Without one of a
template's anchors (its heaviest terms, taken until the rest has a norm below `least`) no unit can
reach `least`, nor can one with so many different words outside the templates that their norm (each weighs 1 at
least) outweighs what its words within can bring; the scan drops such units early and loses nothing.

A licence file gives its licence to its directory. A file without a licence of its own inherits
that of the nearest ancestor directory that has one, by joins of directories with their ancestors;
distinct directories are joined before their files, so a directory of a third of all files is a
row. Two licence files in a directory: the greater score (cosines are rounded to six digits), then the lesser path, wins.

DataFrame expressions only. Null or empty text: no licence of its own. Null path: nothing to
inherit. Repeated rows: each has its own result. Extra columns are ignored. Whole texts are scanned.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import only, written

# Notices that public licences are announced with.
TEMPLATES = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License"),
    ("MIT", "Released under the MIT License"),
    ("MIT", "Licensed under the MIT license"),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3"),
    ("GPL-3.0", "it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version"),
    ("GPL-2.0", "This program is licensed under the GNU General Public License, version 2"),
    ("LGPL-3.0", "This library is licensed under the GNU Lesser General Public License, version 3"),
    ("AGPL-3.0", "This program is licensed under the GNU Affero General Public License, version 3"),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License"),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, version 2.0"),
    ("CC-BY-4.0", "Licensed under CC BY 4.0"),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0"),
    ("CC0-1.0", "Dedicated to the public domain under CC0 1.0"),
]
UNIT = r"\n+|(?<=[.;!?])\s+"
TERM = r"[a-z]+|[0-9]+(?:\.[0-9]+)*"
LICENCE_FILE = r"(?i)(?:^|/)(?:licen[cs]e|copying|notice|copyright|unlicense)(?:[.-][^/]*)?$"


def _terms(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(TERM), F.lit(0))


def _any_of(terms: list[str]) -> str:
    """A pattern for these terms, and for nothing if there are none."""
    return r"(?<![A-Za-z0-9])(?:" + "|".join(re.escape(x) for x in terms) + r")(?![A-Za-z0-9])" if terms else "(?!)"


def vocabulary(templates: DataFrame) -> list[str]:
    """The templates' terms, long ones first."""
    terms = templates.select(F.explode(_terms(F.col("text"))).alias("term")).distinct()
    return [x["term"] for x in terms.orderBy(F.desc(F.length("term")), "term").collect()]


def file_counts(files: DataFrame) -> DataFrame:
    """term, df: how many files hold each term. Summed up in each task first."""
    return files.select(F.explode(F.array_distinct(_terms(F.col("text")))).alias("term")).groupBy("term").agg(F.count("*").alias("df"))


def idf_of(df: Column, n_files: int) -> Column:
    return F.log(F.lit(1.0 + n_files) / (1 + F.coalesce(df, F.lit(0)))) + 1


def template_weights(templates: DataFrame, counts: DataFrame, n_files: int) -> DataFrame:
    """templates(licence, text) -> template, licence, term, idf, weight (unit vectors)."""
    rows = templates.distinct().withColumn("template", F.xxhash64("licence", "text")).select("template", "licence", F.explode(_terms(F.col("text"))).alias("term"))
    tf = rows.groupBy("template", "licence", "term").agg(F.count("*").alias("tf"))
    raw = tf.join(counts, "term", "left").withColumn("idf", idf_of(F.col("df"), n_files)).withColumn("raw", (1 + F.log("tf")) * F.col("idf"))
    return raw.withColumn("weight", F.col("raw") / F.sqrt(F.sum(F.col("raw") * F.col("raw")).over(Window.partitionBy("template")))).drop("raw", "tf", "df")


def anchors(weights: DataFrame, least: float) -> list[str]:
    """The terms of which every unit with a cosine of at least `least` holds one."""
    kept = F.sum(F.col("weight") * F.col("weight")).over(Window.partitionBy("template").orderBy(F.desc("weight"), "term").rowsBetween(Window.unboundedPreceding, -1))
    heavy = weights.withColumn("before", F.coalesce(kept, F.lit(0.0))).where(1 - F.col("before") >= least * least * 0.999)
    return [x["term"] for x in heavy.select("term").distinct().orderBy("term").collect()]  # terms of the templates only


def scan_licences(files: DataFrame, templates: DataFrame, least: float = 0.6, carry: dict[str, str] | None = None) -> DataFrame:
    """files(path, text) with templates(licence, text) -> row, path, (carried,) licence, score,
    via (own, inherited or none), source (the directory inherited from)."""
    base = only(files, path="string", text="string", **(carry or {}))
    terms = vocabulary(templates)
    counts, n_files = written(file_counts(base), "licence-terms"), base.count()
    weights = written(template_weights(templates, counts, n_files), "licence-weights")
    heaviest = weights.agg(F.max("idf").alias("idf")).first()["idf"] or 1.0
    pattern, within = _any_of(anchors(weights, least)), _any_of(terms)
    named = F.coalesce(F.col("path").rlike(LICENCE_FILE), F.lit(False))
    low = F.lower("text")

    def may(u: Column) -> Column:
        """(1 + log tf)^2 <= 1.5 tf: with too few words of the templates no cosine is great enough."""
        known = F.size(F.regexp_extract_all(F.lower(u), F.lit(within), F.lit(0)))
        return F.lower(u).rlike(pattern) & (F.size(F.array_distinct(_terms(u))) <= known * (1 + 1.5 * heaviest**2 * (1 - least**2) / least**2))

    units = F.filter(F.split(F.col("text"), UNIT, -1), may)
    seen = base.select(
        F.monotonically_increasing_id().alias("row"), "path", *(carry or {}), named.alias("named"),
        F.when(low.rlike(pattern), F.concat(units, F.when(named, F.array("text")).otherwise(F.array().cast("array<string>")))).alias("units"),
    )
    rows = written(seen, "licence-units")
    best = _matches(rows, weights, counts, n_files, least)
    own = rows.drop("units").join(best, "row", "left")
    folder = F.regexp_replace("path", r"[^/]*$", "")  # with its closing slash; "" at the top
    rank = F.struct((-F.col("score")).alias("less"), F.col("path"))
    given = own.where(F.col("named") & F.col("licence").isNotNull()).groupBy(folder.alias("folder")).agg(F.min_by("licence", rank).alias("given"), F.max("score").alias("given_score"))
    folders = own.where(F.col("licence").isNull() & F.col("path").isNotNull()).select(folder.alias("folder")).distinct()
    steps = F.split("folder", "/")
    above = folders.select("folder", F.explode(F.transform(F.sequence(F.lit(0), F.size(steps) - 1), lambda k: F.when(k == 0, "").otherwise(F.concat(F.array_join(F.slice(steps, 1, k), "/"), F.lit("/"))))).alias("source"))
    nearest = (
        above.distinct().join(given.withColumnRenamed("folder", "source"), "source")
        .groupBy("folder").agg(F.max(F.struct(F.length("source").alias("depth"), "source", "given", "given_score")).alias("n"))
        .select("folder", "n.source", "n.given", "n.given_score")
    )
    out = own.withColumn("folder", F.when(F.col("licence").isNull(), folder)).join(nearest, "folder", "left")
    return out.select(
        "row", "path", *(carry or {}), F.coalesce("licence", "given").alias("licence"), F.coalesce("score", "given_score").alias("score"),
        F.when(F.col("licence").isNotNull(), "own").when(F.col("given").isNotNull(), "inherited").otherwise("none").alias("via"), "source",
    )


def _matches(rows: DataFrame, weights: DataFrame, counts: DataFrame, n_files: int, least: float) -> DataFrame:
    """row, licence, score: the best template of each row's units."""
    units = rows.where(F.size("units") > 0).select("row", F.posexplode("units").alias("unit", "text"))
    tf = written(units.select("row", "unit", F.explode(_terms(F.col("text"))).alias("term")).groupBy("row", "unit", "term").agg(F.count("*").alias("tf")), "licence-tf")
    held = tf.join(counts, "term", "left").withColumn("w", (1 + F.log("tf")) * idf_of(F.col("df"), n_files))
    norm = held.groupBy("row", "unit").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dots = held.join(weights.select("term", "template", "licence", "weight"), "term").groupBy("row", "unit", "template", "licence").agg(F.sum(F.col("w") * F.col("weight")).alias("dot"), F.count("*").alias("shared")).where("shared >= 2")
    scored = dots.join(norm, ["row", "unit"]).withColumn("score", F.round(F.col("dot") / F.col("norm"), 6)).where(F.col("score") >= least)
    return scored.groupBy("row").agg(F.max(F.struct("score", "licence")).alias("b")).select("row", "b.licence", "b.score")


def default_templates(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(TEMPLATES, "licence string, text string")
