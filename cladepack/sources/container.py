"""Data source `cladepack`: containers as tables of trees, with pruning of blocks by tree id; and plain text forms."""

from __future__ import annotations

import glob
import os

import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual

from ..operators import codec as cd


def read_newick(spark: SparkSession, path: str) -> DataFrame:
    """(tree_id, newick) of text files with one tree a line. Ids follow file name and the order of lines in it, so they are
    the same in every run: a file's offset is the number of trees in the files before it."""
    lines = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("at"), F.monotonically_increasing_id().alias("m")).where(F.trim("value") != "")
    from pyspark.sql import Window

    counts = lines.groupBy("file", "at").agg(F.count("*").alias("n"))
    base = counts.withColumn("base", F.coalesce(F.sum("n").over(Window.orderBy("file", "at").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    ranked = lines.withColumn("k", F.row_number().over(Window.partitionBy("file", "at").orderBy("m")) - 1)
    return ranked.join(F.broadcast(base.select("file", "at", "base")), ["file", "at"]).select((F.col("base") + F.col("k")).alias("tree_id"), F.col("value").alias("newick"))


def write_newick_text(trees: DataFrame, path: str) -> None:
    trees.orderBy("tree_id").select("newick").write.mode("overwrite").text(path)


def write_container(container: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Parquet without page compression: payloads are dense already."""
    container.write.mode(mode).option("compression", "none").parquet(path)


def textrun_lines(container: DataFrame) -> DataFrame:
    """(block_id, line_no, line) of a textrun container: taxa, tree count, bipartition count, then a line for each entry."""
    lines = F.split(F.col("payload").cast("string"), "\n")
    return container.select("block_id", F.posexplode(lines).alias("line_no", "line")).where("line <> ''")


class _Range(InputPartition):
    def __init__(self, file: str, group: int):
        self.file, self.group = file, group


class ContainerSource(DataSource):
    """spark.read.format("cladepack").load(path): (tree_id, newick). path: a folder of containers that all executors can
    read as files; elsewhere read the Parquet with Spark and use codec.decompress, which prunes alike."""

    @classmethod
    def name(cls) -> str:
        return "cladepack"

    def schema(self) -> str:
        return "tree_id bigint, newick string"

    def reader(self, schema):
        return ContainerReader(self.options["path"])


class ContainerReader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.lo, self.hi, self.only = path.removeprefix("file://"), None, None, None

    def pushFilters(self, filters):
        for f in filters:
            column = getattr(f, "attribute", None)
            if column == ("tree_id",):
                if isinstance(f, EqualTo):
                    self._between(f.value, f.value)
                elif isinstance(f, In):
                    self._between(min(f.value), max(f.value))
                elif isinstance(f, GreaterThan | GreaterThanOrEqual):
                    self._between(f.value, None)
                elif isinstance(f, LessThan | LessThanOrEqual):
                    self._between(None, f.value)
            yield f  # Spark filters the rows once more

    def _between(self, lo, hi):
        self.lo = lo if self.lo is None else self.lo if lo is None else max(lo, self.lo)
        self.hi = hi if self.hi is None else self.hi if hi is None else min(hi, self.hi)

    def partitions(self):
        out = []
        for file in sorted(glob.glob(os.path.join(self.path, "**/*.parquet"), recursive=True)):
            meta = pq.ParquetFile(file)
            for g in range(meta.num_row_groups):
                heads = meta.read_row_group(g, columns=["first_tree", "span"])
                first, span = heads.column(0).to_pylist(), heads.column(1).to_pylist()
                if any((self.hi is None or f <= self.hi) and (self.lo is None or f + s > self.lo) for f, s in zip(first, span, strict=True)):
                    out.append(_Range(file, g))
        return out

    def read(self, partition):
        rows = pq.ParquetFile(partition.file).read_row_group(partition.group).to_pylist()
        for row in rows:
            first, span = row["first_tree"], row["span"]
            lo = max(0, (self.lo if self.lo is not None else first) - first)
            hi = min(span, (self.hi if self.hi is not None else first + span) - first + 1)
            if lo >= hi:
                continue
            for piece in cd.Block(row).pieces(1024, first + lo, first + hi - 1):
                ids, texts = zip(*cd.rebuild_piece(piece), strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(texts)], ["tree_id", "newick"])


def register(spark: SparkSession) -> None:
    """Make the format known, with filters reaching it."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(ContainerSource)
