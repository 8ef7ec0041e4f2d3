"""Edge files: tab, CSV, JSON lines and Matrix-Market coordinates."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "src bigint, dst bigint, val double"


def read_edge_text(spark: SparkSession, path: str, form: str) -> DataFrame:
    """(src, dst, val); lines that start with % or # are comments, missing values are null.

    ``mtx`` drops the size line: the first that is not a comment. Its entries are 1-based and kept so.
    """
    if form == "csv":
        return spark.read.schema(SCHEMA).option("comment", "#").csv(path)
    if form == "json":
        return spark.read.schema(SCHEMA).json(path)
    if form not in ("tsv", "mtx"):
        raise ValueError("form is csv, json, tsv or mtx")
    lines = spark.read.text(path, wholetext=form == "mtx")
    if form == "mtx":
        # small headers, large bodies: the size line is told by position, so a file is read whole; split big files before
        body = F.filter(F.split("value", "\\r?\\n"), lambda x: ~x.rlike(r"^\s*(%|$)"))
        lines = lines.select(F.explode(F.slice(body, F.lit(2), F.greatest(F.size(body) - 1, F.lit(0)))).alias("value"))
    parts = lines.filter(~F.col("value").rlike(r"^\s*([%#]|$)")).select(F.split(F.trim("value"), r"\s+").alias("p"))
    return parts.select(F.get("p", F.lit(0)).cast("bigint").alias("src"), F.get("p", F.lit(1)).cast("bigint").alias("dst"), F.get("p", F.lit(2)).cast("double").alias("val"))


def write_edge_text(df: DataFrame, path: str, form: str) -> None:
    out = df.select("src", "dst", *(["val"] if "val" in df.columns else []))
    if form == "json":
        out.write.mode("overwrite").json(path)
    elif form == "csv":
        out.write.mode("overwrite").csv(path)
    else:
        out.select(F.concat_ws("\t", *out.columns).alias("value")).write.mode("overwrite").text(path)
