"""Code footprint: code lines in a declared scope."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

EXCLUDED = r"/(tests?|examples?|scripts?|docs?|vendor(ed)?)/"


def is_code(line: Column) -> Column:
    """Neither blank nor a comment alone; doc-strings count as code."""
    return ~line.rlike(r"^\s*$") & ~line.rlike(r"^\s*#")


def count(spark: SparkSession, paths: list[str], include: str = r"\.py$", exclude: str = EXCLUDED) -> DataFrame:
    """path, lines, code_lines of the files in scope."""
    lines = spark.read.text(paths, recursiveFileLookup=True, pathGlobFilter="*.py").select("value", F.col("_metadata.file_path").alias("path"))
    return lines.filter(F.col("path").rlike(include) & ~F.col("path").rlike(exclude)).groupBy("path").agg(F.count("*").alias("lines"), F.sum(is_code(F.col("value")).cast("long")).alias("code_lines"))
