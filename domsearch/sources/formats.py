"""Readers and sinks for the formats in which found data comes."""

from __future__ import annotations

import decimal

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..store import fresh


def roundtrip(df: DataFrame, fmt: str, schema: str | None = None, **options: str) -> DataFrame:
    """Write in a format and read it back, with a declared schema or, without one, an inferred one."""
    path = fresh(df.sparkSession, fmt)
    df.write.format(fmt).options(**options).save(path)
    reader = df.sparkSession.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader.option("inferSchema", "true")).load(path)


def bucketed(df: DataFrame, name: str, buckets: int, *columns: str) -> DataFrame:
    """A table bucketed and sorted by its join key, so later joins on it need no shuffle."""
    spark = df.sparkSession
    df.write.mode("overwrite").bucketBy(buckets, *columns).sortBy(*columns).option("path", fresh(spark, name)).saveAsTable(name)
    return spark.table(name)


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.domains, self.size = int(options.get("domains", "4")), int(options.get("size", "10"))

    def partitions(self):
        return [_Range(k, k + 1) for k in range(self.domains)]

    def read(self, part):
        for k in range(part.low, part.high):
            for v in range(self.size * (k + 1)):
                yield f"nested:{k}", str(v)


class NestedDomains(DataSource):
    """A source of nested domains of known containment, for tests: domain k holds the first (k + 1) * size integers."""

    @classmethod
    def name(cls) -> str:
        return "nested_domains"

    def schema(self) -> str:
        return "domain_id string, value string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def nested_domains(spark: SparkSession, domains: int = 4, size: int = 10) -> DataFrame:
    spark.dataSource.register(NestedDomains)
    return spark.read.format("nested_domains").option("domains", domains).option("size", size).load()


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


def _text(value) -> str:
    """A value as text: doubles in hundredths, times in ISO form."""
    if isinstance(value, float):
        return str(int(decimal.Decimal(repr(value * 100)).quantize(decimal.Decimal(1), decimal.ROUND_HALF_UP)))
    if hasattr(value, "strftime"):
        return value.strftime("%Y-%m-%d %H:%M:%S" if hasattr(value, "hour") else "%Y-%m-%d")
    return str(value)


class _FileReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.only = options.get("path"), set(filter(None, options.get("files", "").split(",")))

    def _system(self, path: str):
        from pyarrow import fs

        return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)

    def partitions(self):
        from pyarrow import fs

        system, root = self._system(self.path)
        found = sorted(x.path for x in system.get_file_info(fs.FileSelector(root, recursive=True)) if x.type == fs.FileType.File and x.extension in ("parquet", "csv"))
        return [_File(x) for x in found if not self.only or x.rsplit("/", 1)[-1] in self.only]

    def read(self, part):
        import pyarrow as pa
        import pyarrow.csv
        import pyarrow.parquet

        system, _ = self._system(self.path)
        name = part.path.rsplit("/", 1)[-1].rsplit(".", 1)[0]
        with system.open_input_file(part.path) as f:
            if part.path.endswith(".csv"):
                columns = pa.csv.read_csv(f)
                batches = columns.to_batches(max_chunksize=65_536)
            else:
                batches = pa.parquet.ParquetFile(f).iter_batches(65_536)
            for batch in batches:
                for column, values in zip(batch.schema, batch.columns, strict=True):
                    if pa.types.is_nested(column.type):
                        continue
                    for value in values.unique().to_pylist():
                        if value is not None and (text := _text(value)) != "":
                            yield f"{name}.{column.name}", text


class DomainFiles(DataSource):
    """Entries of every scalar column of the Parquet and CSV files under a path, one partition for each file.

    Options: ``path``; ``files``, names of the files to take, comma-separated (default all).  Values are made distinct
    in each batch of a file; ``distinct`` on the result does the rest.
    """

    @classmethod
    def name(cls) -> str:
        return "domain_files"

    def schema(self) -> str:
        return "domain_id string, value string"

    def reader(self, schema) -> DataSourceReader:
        return _FileReader(self.options)


def domain_files(spark: SparkSession, path: str, files: tuple[str, ...] = ()) -> DataFrame:
    spark.dataSource.register(DomainFiles)
    return spark.read.format("domain_files").option("files", ",".join(files)).option("path", path).load()
