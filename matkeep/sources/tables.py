"""Sources and sinks: tables with pruned columns, fact files in several formats, k-ary fact lines as a data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..lang import _split


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: str | None = None) -> DataFrame:
    """A table with only the columns named; the condition reaches the Parquet scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where else df
    return df.select(*columns) if columns else df


def read_facts(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """Facts from parquet, csv, json, orc or text files (or ``facts`` lines) with a stated schema."""
    return spark.read.format(fmt).schema(schema).load(path)


def write_facts(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", partition_by: list[str] | None = None) -> None:
    out = df.write.format(fmt).mode(mode)
    (out.partitionBy(*partition_by) if partition_by else out).save(path)


class FactLines(DataSource):
    """Lines such as ``edge(1, 'a')`` as rows pred, args; option ``lines`` holds them, separated by line ends."""

    @classmethod
    def name(cls) -> str:
        return "facts"

    def schema(self) -> str:
        return "pred string, args array<string>"

    def reader(self, schema) -> DataSourceReader:
        return _FactLinesReader(self.options)


class _FactLinesReader(DataSourceReader):
    def __init__(self, options):
        self.lines = [x for x in options.get("lines", "").split("\n") if x.strip()]
        self.parts = int(options.get("parts", "2"))

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        for line in self.lines[partition.value :: self.parts]:
            pred, _, rest = line.strip().removesuffix(".").rstrip().partition("(")
            yield pred.strip(), [_bare(a) for a in _split(rest.removesuffix(")"))]


def _bare(arg: str) -> str:
    """Without the quotes around it."""
    return arg[1:-1] if len(arg) > 1 and arg[0] == arg[-1] and arg[0] in "'\"" else arg
