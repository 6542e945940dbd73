"""Text formats and sinks: net lists, signed clauses, coordinate matrices, a Python data source, output by block."""

from __future__ import annotations

import io

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.shape import dense_ids


def _numbered(spark: SparkSession, path: str) -> DataFrame:
    """Lines with a dense net_id in file order."""
    lines = spark.read.text(path).withColumn("at", F.monotonically_increasing_id())
    return dense_ids(lines, F.col("at"), name="net_id").select("net_id", F.trim("value").alias("line"))


def read_netlist(spark: SparkSession, path: str) -> DataFrame:
    """One net a line, vertex ids between blanks; # starts a comment line."""
    lines = _numbered(spark, path).filter("line <> '' AND NOT startswith(line, '#')")
    return lines.select("net_id", F.explode(F.split("line", r"\s+").cast("array<bigint>")).alias("vertex_id")).distinct()


def stream_netlist(spark: SparkSession, path: str) -> DataFrame:
    """Vertex lines as they come in a folder of text files: 'vertex net net ...' -> stream_id, seq, vertex_id, nets.

    A vertex's id is its place in the stream as well: files are written by arrival."""
    words = F.split(F.trim("value"), r"\s+").cast("array<bigint>")
    lines = spark.readStream.text(path).filter("trim(value) <> '' AND NOT startswith(trim(value), '#')").select(words.alias("w"))
    return lines.select(F.lit(1).cast("bigint").alias("stream_id"), F.col("w")[0].alias("seq"), F.col("w")[0].alias("vertex_id"), F.slice("w", 2, F.greatest(F.size("w") - 1, F.lit(0))).alias("nets"))


def read_signed_clauses(spark: SparkSession, path: str) -> DataFrame:
    """CNF-like: literals between blanks, negative ones complemented, 0 ends the clause, c and p lines are skipped."""
    lines = _numbered(spark, path).filter("line <> '' AND substr(line, 1, 1) NOT IN ('c', 'p')")
    literal = F.explode(F.split("line", r"\s+").cast("array<bigint>"))
    return lines.select("net_id", literal.alias("x")).filter("x <> 0").select("net_id", F.abs("x").alias("vertex_id")).distinct()


def read_coordinates(spark: SparkSession, path: str) -> DataFrame:
    """Coordinate matrix: 'row column value' lines after % comments and one size line; rows are nets, columns vertices."""
    lines = spark.read.text(path).filter("NOT startswith(value, '%')").withColumn("at", F.monotonically_increasing_id())
    cells = dense_ids(lines, F.col("at"), name="n").filter("n > 0").select(F.split(F.trim("value"), r"\s+").alias("c"))
    return cells.select(F.col("c")[0].cast("bigint").alias("net_id"), F.col("c")[1].cast("bigint").alias("vertex_id")).distinct()


def write_netlist(pins: DataFrame, path: str) -> None:
    nets = pins.groupBy("net_id").agg(F.concat_ws(" ", F.transform(F.sort_array(F.collect_list("vertex_id")), lambda x: x.cast("string"))).alias("value"))
    nets.select("value").write.text(path)


def write_blocks(df: DataFrame, assign: DataFrame, path: str, key: str, tasks: int = 8) -> None:
    """The rows of df in one folder per block of their key: what a partition is for. assign: vertex_id, block.

    tasks: how many write each block, dealt by a hash of the key."""
    routed = df.join(assign.select(F.col("vertex_id").alias(key), "block"), key)
    routed.repartition("block", F.pmod(F.xxhash64(key), F.lit(tasks))).write.partitionBy("block").parquet(path)


def drain(df: DataFrame) -> None:
    """Run a plan and throw its rows away: for timing."""
    df.write.format("noop").mode("overwrite").save()


def _located(path: str):
    """File system and path for a local path or any address that Arrow knows (file, hdfs, s3, gs)."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path)


class _Range(InputPartition):
    def __init__(self, first: int, end: int):
        self.first, self.end = first, end


class _NetlistReader(DataSourceReader):
    def __init__(self, path: str, size: int):
        self.path, self.size = path, size

    def partitions(self):
        files, name = _located(self.path)
        total = files.get_file_info(name).size
        return [_Range(a, min(total, a + self.size)) for a in range(0, total, self.size)] or [_Range(0, 0)]

    def read(self, part):
        """Lines that begin in the range; the net's id is the byte where its line begins."""
        files, name = _located(self.path)
        with io.BufferedReader(files.open_input_file(name)) as f:
            at = part.first
            if at:
                f.seek(at - 1)
                at += len(f.readline()) - 1
            while at < part.end and (line := f.readline()):
                for x in line.split():
                    yield at, int(x)
                at += len(line)


class NetlistSource(DataSource):
    """spark.read.format('netlist').option('path', file): pins of a net-list file, read by byte ranges.

    The file must be where driver and executors both reach it: a shared folder or a store that Arrow knows by its address."""

    @classmethod
    def name(cls):
        return "netlist"

    def schema(self):
        return "net_id bigint, vertex_id bigint"

    def reader(self, schema):
        return _NetlistReader(self.options["path"], int(self.options.get("range_bytes", 8 << 20)))
