"""Batch and streaming sources."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the folder; columns and filters are pruned at the scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_text(spark: SparkSession, path: str, fmt: str = "text", schema: str | None = None, whole: bool = False) -> DataFrame:
    """Text, CSV, JSON or ORC files; ``whole`` keeps one text file in one row."""
    reader = spark.read.format(fmt)
    if schema:
        reader = reader.schema(schema)
    if fmt == "text" and whole:
        reader = reader.option("wholetext", True)
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.load(path)


def stream_table(spark: SparkSession, sf_dir: str, name: str, per_trigger: int = 1) -> DataFrame:
    """A table as an unbounded source of files."""
    schema = load(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).option("recursiveFileLookup", True).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/{name}.parquet")


def symbol_rate(spark: SparkSession, rps: int, alphabet: str, key: str = "rate") -> DataFrame:
    """Endless symbols that cycle through an alphabet."""
    symbols = F.array(*[F.lit(c) for c in alphabet])
    rows = spark.readStream.format("rate").option("rowsPerSecond", rps).load()
    return rows.select(F.lit(key).alias("stream_id"), F.col("value").alias("seq"), F.col("timestamp").alias("ts"), F.element_at(symbols, (F.col("value") % len(alphabet) + 1).cast("int")).alias("sym"))


class _Range(InputPartition):
    def __init__(self, begin: int, end: int):
        self.begin, self.end = begin, end


def _rows(text: str, begin: int, end: int) -> Iterator[tuple]:
    return ((i, text[i % len(text)]) for i in range(begin, end))


class _Batch(DataSourceReader):
    def __init__(self, options: dict):
        self.text, self.n, self.parts = options["text"], int(options.get("n", len(options["text"]))), int(options.get("partitions", 2))

    def partitions(self) -> list[InputPartition]:
        step = max(1, -(-self.n // self.parts))
        return [_Range(i, min(self.n, i + step)) for i in range(0, self.n, step)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        return _rows(self.text, partition.begin, partition.end)


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, options: dict):
        self.text, self.step = options["text"], int(options.get("step", 100))

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        return _rows(self.text, start["at"], start["at"] + self.step), {"at": start["at"] + self.step}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return _rows(self.text, start["at"], end["at"])


class SymbolSource(DataSource):
    """``format("symbols")``: a text's symbols in a cycle, in batch or as a stream."""

    @classmethod
    def name(cls) -> str:
        return "symbols"

    def schema(self) -> str:
        return "seq bigint, sym string"

    def reader(self, schema) -> DataSourceReader:
        return _Batch(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(self.options)


def register_source(spark: SparkSession) -> None:
    spark.dataSource.register(SymbolSource)
