"""Triples in files: line-based text, CSV, JSON, ORC and Parquet, and sinks for each."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "s string, p string, o string"
#: A subject and a predicate in angle brackets; an object likewise or quoted; a full stop.
LINE = r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)")\s*\.\s*$'


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """s, p, o, malformed: lines that don't parse come whole in the last column, the others have it null."""
    lines = spark.read.text(path).where("trim(value) <> '' AND NOT startswith(trim(value), '#')")
    quoted = F.regexp_extract("value", LINE, 4)
    unescaped = F.replace(F.replace(F.replace(F.replace(quoted, F.lit("\\\\"), F.lit("\x00")), F.lit('\\"'), F.lit('"')), F.lit("\\n"), F.lit("\n")), F.lit("\x00"), F.lit("\\"))
    ok = F.col("value").rlike(LINE)
    part = lambda i: F.when(ok, F.regexp_extract("value", LINE, i))
    return lines.select(part(1).alias("s"), part(2).alias("p"), F.when(ok, F.when(F.regexp_extract("value", LINE, 3) != "", F.regexp_extract("value", LINE, 3)).otherwise(unescaped)).alias("o"), F.when(~ok, F.col("value")).alias("malformed"))


def write_ntriples(t: DataFrame, path: str) -> None:
    escaped = F.replace(F.replace(F.replace(F.col("o"), F.lit("\\"), F.lit("\\\\")), F.lit('"'), F.lit('\\"')), F.lit("\n"), F.lit("\\n"))
    t.select(F.concat(F.lit("<"), "s", F.lit("> <"), "p", F.lit('> "'), escaped, F.lit('" .')).alias("value")).write.text(path)


def read_triples(spark: SparkSession, path: str, form: str) -> DataFrame:
    """csv, json, orc or parquet with a given schema; bad records are kept apart by the reader, never guessed at."""
    reader = spark.read.schema(SCHEMA)
    if form == "csv":
        return reader.option("mode", "PERMISSIVE").option("escape", '"').option("multiLine", "true").csv(path)
    if form == "json":
        return reader.option("mode", "PERMISSIVE").json(path)
    return reader.format(form).load(path)


def write_triples(t: DataFrame, path: str, form: str) -> None:
    if form == "ntriples":
        write_ntriples(t, path)
    elif form == "csv":
        t.write.option("escape", '"').csv(path)
    elif form == "partitioned":
        t.write.partitionBy("p").parquet(path)
    else:
        t.write.format(form).save(path)


def round_trip(t: DataFrame, form: str) -> DataFrame:
    """Written in a form and read again."""
    import uuid

    from triplefed.storage import root

    path = f"{root(t.sparkSession)}/formats/{uuid.uuid4().hex}"
    if form == "bucketed":
        name = f"triplefed_{uuid.uuid4().hex}"
        t.select("s", "p", "o").write.format("parquet").bucketBy(8, "s").sortBy("s").option("path", path).saveAsTable(name)
        return t.sparkSession.table(name)
    write_triples(t.select("s", "p", "o"), path, form)
    if form == "ntriples":
        return read_ntriples(t.sparkSession, path).where("malformed IS NULL").drop("malformed")
    if form == "partitioned":
        return t.sparkSession.read.schema("s string, o string, p string").parquet(path).select("s", "p", "o")
    return read_triples(t.sparkSession, path, form)
