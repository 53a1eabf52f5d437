"""Reading and writing edge lists."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.edges import pairs

_DATA = re.compile(r"\s*[0-9-]")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", src: str = "src", dst: str = "dst") -> DataFrame:
    """Edges from parquet, orc, csv (with a header), json, or plain text.

    ``text``: two ids a line between white space; ``coordinate``: the same after one line
    of sizes at the top of each file; weights behind the ids are ignored. Lines that begin with % or # are comments; further fields are ignored.
    """
    if fmt in ("parquet", "orc"):
        return pairs(spark.read.format(fmt).load(path), src, dst)
    if fmt in ("csv", "json"):
        schema = f"`{src}` long, `{dst}` long"
        return pairs(spark.read.format(fmt).schema(schema).options(header=True).load(path), src, dst)
    if fmt not in ("text", "coordinate"):
        raise ValueError(f"unknown format {fmt}")
    rows = spark.read.text(path)
    is_data = F.col("value").rlike(r"^\s*[0-9-]")
    if fmt == "coordinate":
        # The size line is the first line of a file that is no comment, whatever its numbers are.
        rows = rows.select("value", F.col("_metadata.file_path").alias("_file"))
        first = first_lines(spark, [r["_file"] for r in rows.select("_file").distinct().collect()])  # one row per file
        rows = rows.where(is_data)
        sized = rows.join(F.broadcast(first), (rows["_file"] == first["_name"]) & (rows["value"] == first["_line"]), "left")
        # Lines equal to it are edges but for one: all but one come back (an equal entry repeats the same edge).
        size_like = sized.where("_line IS NOT NULL").groupBy("_file", "value").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("value")
        rows = sized.where("_line IS NULL").select("value").unionByName(size_like)
    else:
        rows = rows.where(is_data)
    fields = F.split(F.trim("value"), r"\s+")
    return rows.select(F.get(fields, F.lit(0)).cast("long").alias("src"), F.get(fields, F.lit(1)).cast("long").alias("dst"))


def first_lines(spark: SparkSession, names: list[str]) -> DataFrame:
    """(_name, _line): the first line of each file that is no comment; the driver opens each file and reads no further."""
    out = []
    sc = spark.sparkContext
    for name in names:
        p = sc._jvm.org.apache.hadoop.fs.Path(sc._jvm.java.net.URI(name))
        stream = p.getFileSystem(sc._jsc.hadoopConfiguration()).open(p)
        codec = sc._jvm.org.apache.hadoop.io.compress.CompressionCodecFactory(sc._jsc.hadoopConfiguration()).getCodec(p)
        reader = sc._jvm.java.io.BufferedReader(sc._jvm.java.io.InputStreamReader(codec.createInputStream(stream) if codec else stream, "UTF-8"))
        try:
            line = reader.readLine()
            while line is not None and not _DATA.match(line):
                line = reader.readLine()
        finally:
            reader.close()
        if line is not None:
            out.append((name, line))
    return spark.createDataFrame(out, "_name string, _line string")


def write_edges_bucketed(edges: DataFrame, table: str, buckets: int) -> DataFrame:
    """A table bucketed and sorted by ``dst``: one shuffle now, none for products later."""
    edges.write.bucketBy(buckets, "dst").sortBy("dst").mode("overwrite").saveAsTable(table)
    return edges.sparkSession.table(table)
