"""Edge lists, adjacency lists, matrices and part vectors in files.

Formats of edges: ``text`` (ends, and perhaps a weight, apart by blanks; ``#`` and ``%`` begin comments), ``csv``, ``json``
(a line each), ``parquet``, ``orc``, ``matrix`` (coordinate text with a banner and a line of sizes, entries from 1) and
``adjacency`` (Parquet, a vertex and an array of its larger neighbours). Every file is written by all tasks at once.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphparts.operators.graph import Graph

FORMATS = ("text", "csv", "json", "parquet", "orc", "matrix", "adjacency")


def _split(lines: DataFrame, base: int) -> DataFrame:
    x = F.split(F.trim("value"), r"[\s,]+")
    return lines.select((F.get(x, F.lit(0)).cast("bigint") - base).alias("src"), (F.get(x, F.lit(1)).cast("bigint") - base).alias("dst"), F.coalesce(F.get(x, F.lit(2)).try_cast("bigint"), F.lit(1)).alias("w"))


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """``(src, dst, w)`` as written; the weight is 1 where there is none."""
    if fmt not in FORMATS:
        raise ValueError(f"unknown format: {fmt}")
    if fmt == "text":
        return _split(spark.read.text(path).where(~F.col("value").rlike(r"^\s*([#%].*)?$")), 0)
    if fmt == "matrix":
        lines = spark.read.text(path).withColumn("file", F.col("_metadata.file_path")).withColumn("n", F.monotonically_increasing_id())
        entries = lines.where(~F.col("value").rlike(r"^\s*(%.*)?$"))
        bannered = lines.where(F.col("value").startswith("%%MatrixMarket")).select("file").distinct()
        sizes = entries.join(F.broadcast(bannered), "file").groupBy("file").agg(F.min("n").alias("n"))  # the line after a file's banner
        return _split(entries.join(F.broadcast(sizes.select("n")), "n", "left_anti").select("value"), 1)
    if fmt == "adjacency":
        return spark.read.parquet(path).select(F.col("v").alias("src"), F.explode("near").alias("dst"), F.lit(1).cast("bigint").alias("w"))
    schema = "src bigint, dst bigint, w bigint"
    return {"csv": lambda: spark.read.schema(schema).option("header", True).csv(path), "json": lambda: spark.read.schema(schema).json(path), "parquet": lambda: spark.read.parquet(path), "orc": lambda: spark.read.orc(path)}[fmt]().select("src", "dst", F.coalesce("w", F.lit(1)).alias("w"))


def write_edges(g: Graph, path: str, fmt: str = "parquet") -> None:
    """The edges of ``g`` in ``path``, a folder that must not exist."""
    if fmt not in FORMATS:
        raise ValueError(f"unknown format: {fmt}")
    e = g.edges.select("src", "dst", "w")
    if fmt == "text":
        e.select(F.concat_ws("\t", "src", "dst", "w").alias("value")).write.text(path)
    elif fmt == "matrix":
        m, top = e.agg(F.count("*"), F.coalesce(F.max("dst"), F.lit(-1))).first()
        head = f"%%MatrixMarket matrix coordinate integer symmetric\n{top + 1} {top + 1} {m}"
        e.sparkSession.createDataFrame([(head,)], "value string").coalesce(1).write.text(path)
        e.select(F.concat_ws(" ", F.col("src") + 1, F.col("dst") + 1, "w").alias("value")).write.mode("append").text(path)
    elif fmt == "adjacency":
        e.groupBy(F.col("src").alias("v")).agg(F.collect_list("dst").alias("near")).write.parquet(path)
    elif fmt == "csv":
        e.write.option("header", True).csv(path)
    else:
        e.write.format(fmt).save(path)


def write_parts(parts: DataFrame, path: str, fmt: str = "vector") -> None:
    """``vector``: a line ``v,part`` for each vertex; ``parquet``: a folder for each part."""
    if fmt == "vector":
        parts.select("v", "part").write.csv(path)
    elif fmt == "parquet":
        parts.select("v", "part").repartition("part").write.partitionBy("part").parquet(path)
    else:
        raise ValueError(f"unknown format: {fmt}")


def read_parts(spark: SparkSession, path: str, fmt: str = "vector") -> DataFrame:
    if fmt not in ("vector", "parquet"):
        raise ValueError(f"unknown format: {fmt}")
    read = spark.read.schema("v bigint, part int")
    return read.csv(path) if fmt == "vector" else read.parquet(path)


def write_metrics(quality: DataFrame, path: str) -> None:
    """Measures as JSON, a line each."""
    quality.write.json(path)


def bucketed_arcs(g: Graph, table: str, buckets: int = 64) -> DataFrame:
    """The arcs as a table of the session's warehouse, bucketed and sorted by ``u``: joins of labels on ``u`` need not shuffle it."""
    g.arcs.write.mode("overwrite").bucketBy(buckets, "u").sortBy("u").format("parquet").saveAsTable(table)
    return g.edges.sparkSession.table(table)
