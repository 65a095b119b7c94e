"""File sources and sinks with declared schemas, a Python data source for quads, and the SQL surface."""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from cellscrub.functions.text import decodings_of
from cellscrub.session import scratch_dir


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """df written as json, csv, orc or parquet to the shared folder and read with its schema."""
    path = f"{scratch_dir(df.sparkSession)}/files-{uuid.uuid4().hex}"
    options = {"csv": {"header": "true", "quoteAll": "true", "escape": '"', "nullValue": "\\N", "emptyValue": ""}}.get(kind, {})
    df.write.options(**options).format(kind).save(path)
    return df.sparkSession.read.schema(df.schema).options(**options).format(kind).load(path)


def write_partitioned(df: DataFrame, path: str, by: str) -> DataFrame:
    """Parquet partitioned by a column, one file a value and task at most; read back with partition pruning."""
    df.repartition(by).sortWithinPartitions(by).write.mode("overwrite").partitionBy(by).parquet(path)
    return df.sparkSession.read.parquet(path)


class QuadSource(DataSource):
    """`spark.read.format("quads").load(folder)`: one partition a file, lines split in Python.

    The built-in path is `quads.read_quads`; this one shows where a custom reader plugs in.
    """

    @classmethod
    def name(cls) -> str:
        return "quads"

    def schema(self) -> str:
        return "subject string, predicate string, object string, graph_iri string"

    def reader(self, schema: T.StructType) -> DataSourceReader:
        return _QuadReader(self.options["path"])


class _QuadReader(DataSourceReader):
    _line = re.compile(r'^(\S+) <([^>]*)> (?:"((?:[^"\\]|\\.)*)"|<([^>]*)>|(_:\S+)) <([^>]*)> \.$')

    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        import os

        return [InputPartition(f"{self.path}/{f}") for f in sorted(os.listdir(self.path)) if f.endswith(".txt")]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        with open(partition.value, encoding="utf-8") as lines:
            for line in lines:
                if m := self._line.match(line.rstrip("\n")):
                    text = re.sub(r'\\(["\\])', r"\1", m[3]) if m[3] is not None else m[4] or m[5]
                    yield m[1], m[2], text, m[6]


@F.udtf(returnType=T.StructType([T.StructField("step", T.IntegerType()), T.StructField("decoded", T.StringType())]))
class Decodings:
    """Table function: what a value may have been before it was wrongly encoded."""

    def eval(self, value: str):
        for i, d in enumerate(decodings_of(value or "")):
            yield i, d


def register(spark: SparkSession, tables: dict[str, DataFrame]) -> None:
    """Views by name, and the table function `decodings`, for use from SQL."""
    for name, df in tables.items():
        df.createOrReplaceTempView(name)
    spark.udtf.register("decodings", Decodings)


CATEGORY_REPORT = "SELECT attr, category, count(*) AS n FROM {cells} WHERE attr = :attr GROUP BY attr, category"


def category_report(cells: DataFrame, attr: str) -> DataFrame:
    """The parameterised SQL form of a category table."""
    return cells.sparkSession.sql(CATEGORY_REPORT, args={"attr": attr}, cells=cells)
