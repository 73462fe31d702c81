"""Sources and sinks of graphs: tables, edge lists, matrix-market and road files, bucketed tables, generator source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from starforest.graph.order import canonical_edges
from starforest.runtime import read_table

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def read_columns(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table with nothing but the named columns read."""
    df = read_table(spark, sf_dir, name)
    return df.select(*columns) if columns else df


def read_edge_list(spark: SparkSession, path: str, *, comment: str = "#", default_weight: int = 1) -> DataFrame:
    """``(lo, hi, w)`` from lines ``a b [w]`` separated by white space, comments skipped."""
    f = F.split(F.trim("value"), r"\s+")
    rows = spark.read.text(path).where(~F.col("value").startswith(comment) & (F.trim("value") != "")).select(f.alias("f"))
    w = F.coalesce(F.try_element_at("f", F.lit(3)).cast("long"), F.lit(default_weight).cast("long"))
    return canonical_edges(rows.select(F.col("f")[0].cast("long").alias("a"), F.col("f")[1].cast("long").alias("b"), w.alias("w")))


def read_matrix_market(spark: SparkSession, path: str) -> DataFrame:
    """``(lo, hi, w)`` from a coordinate file; ids as in the file (from 1). The size line is the one after the comments."""
    lines = spark.read.text(path).select("value", F.col("_metadata.file_block_start").alias("at")).where(~F.col("value").startswith("%"))
    lines = lines.select("at", F.monotonically_increasing_id().alias("id"), F.split(F.trim("value"), r"\s+").alias("f"))
    # Blocks of a file need not be numbered in the file's order; the first one starts at 0.
    size = lines.where("at = 0").agg(F.min("id")).first()[0]
    w = F.coalesce(F.try_element_at("f", F.lit(3)).cast("double").cast("long"), F.lit(1).cast("long"))
    return canonical_edges(lines.where(F.col("id") != (size if size is not None else -1)).select(F.col("f")[0].cast("long").alias("a"), F.col("f")[1].cast("long").alias("b"), w.alias("w")))


def read_road_text(spark: SparkSession, path: str) -> DataFrame:
    """``(lo, hi, w)`` from arc lines ``a tail head weight``."""
    arc = r"^a (\d+) (\d+) (-?\d+)"
    rows = spark.read.text(path).where(F.col("value").startswith("a "))
    return canonical_edges(rows.select(*[F.regexp_extract("value", arc, k).cast("long").alias(c) for k, c in ((1, "a"), (2, "b"), (3, "w"))]))


def read_json_edges(spark: SparkSession, path: str) -> DataFrame:
    return canonical_edges(spark.read.schema("a long, b long, w long").json(path))


def from_rows(spark: SparkSession, rows: list[tuple[int, int, int]]) -> DataFrame:
    return canonical_edges(spark.createDataFrame(rows, "a long, b long, w long"))


def relabel_dense(spark: SparkSession, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """String ids to LONG: ``(edges(lo, hi, w), names(v, name))``; ids ascend with the names' binary order."""
    names = edges.select(F.explode(F.array("a", "b")).alias("name")).distinct().repartitionByRange("name").sortWithinPartitions("name")
    from starforest.runtime import cut_state

    names = cut_state(names.select(F.monotonically_increasing_id().alias("v"), "name"))
    x, y = (names.select(F.col("name").alias(c), F.col("v").alias(f"v{c}")) for c in "ab")
    return canonical_edges(edges.join(x, "a").join(y, "b").select(F.col("va").alias("a"), F.col("vb").alias("b"), "w")), names


def write_edges(edges: DataFrame, table: str, *, buckets: int = 8, path: str | None = None) -> None:
    """A table bucketed and sorted by ``lo``: later joins on it need no exchange. ``path``: its folder, else the warehouse's."""
    w = edges.write.mode("overwrite").bucketBy(buckets, "lo").sortBy("lo")
    (w.option("path", path) if path else w).saveAsTable(table)


def write_forest(result, path: str) -> None:
    result.forest.write.mode("overwrite").partitionBy("iteration").parquet(path)


def write_trace(result, path: str) -> None:
    result.trace_frame().coalesce(1).write.mode("overwrite").json(path)


class _Share(InputPartition):
    def __init__(self, start: int, end: int) -> None:
        self.start, self.end = start, end


class _UniformReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.n, self.m, self.seed, self.parts = (int(options.get(k, d)) for k, d in (("n", 1000), ("m", 4000), ("seed", 1), ("parts", 4)))

    def partitions(self) -> list[InputPartition]:
        return [_Share(self.m * k // self.parts, self.m * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, partition: _Share):
        for i in range(partition.start, partition.end):
            yield *(_mix(self.seed, i, k) % s for k, s in ((1, self.n), (2, self.n))), _mix(self.seed, i, 3) % 255 + 1, i


def _mix(*parts: int) -> int:
    h = 17
    for p in parts:
        h = (h * 69_069 + p % 2_147_483_647 + 1) % 2_147_483_647
        h = (h * h + 48_271) % 2_147_483_647
    return (h * 16_807 + h // 8_191) % 2_147_483_647


class UniformSource(DataSource):
    """``spark.read.format('uniform_graph')``: the rows of :func:`starforest.graph.generators.uniform_graph` before merging."""

    @classmethod
    def name(cls) -> str:
        return "uniform_graph"

    def schema(self) -> str:
        return "a long, b long, w long, id long"

    def reader(self, schema) -> DataSourceReader:
        return _UniformReader(self.options)


def register_sources(spark: SparkSession) -> None:
    spark.dataSource.register(UniformSource)
