"""Where relations come from: frames, tables, files, databases and a source in Python; and where derived facts go."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .facts import as_fact_lines, read_fact_text


class EdbCatalog:
    """Relations by name. A driver takes relations()."""

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.bound: dict[str, DataFrame] = {}

    def bind(self, pred: str, source: DataFrame | str | list[tuple], schema: str | None = None) -> EdbCatalog:
        """source: a frame, the name of a table or view, or rows with a schema."""
        if isinstance(source, DataFrame):
            self.bound[pred] = source
        elif isinstance(source, str):
            self.bound[pred] = self.spark.table(source)
        else:
            self.bound[pred] = self.spark.createDataFrame(source, schema)
        return self

    def read(self, pred: str, fmt: str, path: str, schema: str | None = None, arity: int | None = None, **options) -> EdbCatalog:
        """fmt: parquet, csv, json, or facts (lines `pred(a, 'b').` of an arity)."""
        if fmt == "facts":
            self.bound[pred] = read_fact_text(self.spark, path, pred, arity)
            return self
        reader = self.spark.read.format(fmt).options(**options)
        self.bound[pred] = (reader.schema(schema) if schema else reader).load(path)
        return self

    def jdbc(self, pred: str, url: str, query: str, column: str | None = None, bounds: tuple[int, int] | None = None, parts: int = 8, **options) -> EdbCatalog:
        """A query on a database; with a column and its bounds it is read in parts."""
        reader = self.spark.read.format("jdbc").options(url=url, dbtable=f"({query}) q", **options)
        if column and bounds:
            reader = reader.options(partitionColumn=column, lowerBound=bounds[0], upperBound=bounds[1], numPartitions=parts)
        self.bound[pred] = reader.load()
        return self

    def relations(self) -> dict[str, DataFrame]:
        return dict(self.bound)


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class ChainSource(DataSource):
    """Edges of chains: i -> i + 1 for i below `length`, from each of `chains` starts, made where they are read; `lengths` names a length for each chain."""

    @classmethod
    def name(cls) -> str:
        return "rulepush_chains"

    def schema(self) -> str:
        return "c0 long, c1 long"

    def reader(self, schema) -> DataSourceReader:
        length, chains, parts = (int(self.options.get(k, v)) for k, v in (("length", 10), ("chains", 1), ("parts", 4)))
        lengths = [int(x) for x in self.options["lengths"].split(",") if x] if "lengths" in self.options else [length] * chains
        chains, length = len(lengths), max(lengths, default=0)

        class Reader(DataSourceReader):
            def partitions(self):
                cuts = [chains * i // parts for i in range(parts + 1)]
                return [_Range(a, b) for a, b in zip(cuts, cuts[1:]) if a < b]

            def read(self, partition) -> Iterator[tuple]:
                for c in range(partition.lo, partition.hi):
                    base = c * (length + 1)
                    for i in range(base, base + lengths[c]):
                        yield i, i + 1

        return Reader()


def write(df: DataFrame, path: str, fmt: str = "parquet", pred: str = "fact", by: list[str] | None = None) -> None:
    """Derived facts as parquet, csv, json or fact text, in folders by columns where `by` names some; noop goes nowhere."""
    if fmt == "facts":
        as_fact_lines(df, pred).write.text(path)
        return
    out = df.write.format(fmt).mode("overwrite" if fmt == "noop" else "error")
    (out.partitionBy(*by) if by else out).save(*([] if fmt == "noop" else [path]))
