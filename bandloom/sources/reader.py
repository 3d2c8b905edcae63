"""A saved filter as a Spark data source, and its bits as a table function.

spark.dataSource.register(FilterSource); spark.read.format("bandfilter").option("path", ...).load() gives the blocks (or, with
option("part", "meta"), the metadata) of a filter that catalog.save wrote to a path that all executors see.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.dataset as ds
import pyarrow.fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from bandloom.operators.build import BLOCKS, META
from bandloom.runtime import ship

PARTS = {"blocks": BLOCKS, "meta": META}


class FilterSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "bandfilter"

    def schema(self) -> str:
        part = self.options.get("part", "blocks")
        if part not in PARTS:
            raise ValueError(f"part is one of {sorted(PARTS)}")
        return PARTS[part]

    def reader(self, schema) -> FilterReader:
        return FilterReader(self.options["path"], self.options.get("part", "blocks"), [f.name for f in schema.fields])


class FilterReader(DataSourceReader):
    """One input partition for each file of the part."""

    def __init__(self, path: str, part: str, columns: list[str]):
        self.path, self.part, self.columns = path, part, columns

    def partitions(self) -> list[InputPartition]:
        fs, folder = pyarrow.fs.FileSystem.from_uri(f"{self.path}/{self.part}" if ":" in self.path else f"file://{self.path}/{self.part}")
        files = [f.path for f in fs.get_file_info(pyarrow.fs.FileSelector(folder)) if f.is_file and not f.base_name.startswith(("_", "."))]
        return [InputPartition((fs.type_name, f)) for f in sorted(files)] or [InputPartition(None)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        if partition.value is None:
            return
        scheme, path = partition.value
        fs = pyarrow.fs.LocalFileSystem() if scheme == "local" else pyarrow.fs.FileSystem.from_uri(self.path)[0]
        yield from ds.dataset(path, filesystem=fs, format="parquet").to_batches(columns=self.columns)


@F.udtf(returnType="row_number long, column_number int, bit int")
class FilterBits:
    """The bits of one block's words, a row each: for SQL's LATERAL over <prefix>_blocks."""

    def eval(self, block: int, words: list[int]):
        for j, word in enumerate(words or []):
            for i in range(64):
                yield block * 64 + i, j, (word >> i) & 1


def register(spark: SparkSession) -> None:
    """The format "bandfilter", and the table function filter_bits(block, words)."""
    ship(spark)
    spark.dataSource.register(FilterSource)
    spark.udtf.register("filter_bits", FilterBits)


def dump(spark: SparkSession, view: str) -> DataFrame:
    """Every bit of a filter whose blocks are a view, by the table function."""
    return spark.sql(f"SELECT segment, t.* FROM {view}, LATERAL filter_bits(block, words) t")
