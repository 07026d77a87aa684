"""A Python data source of multi-vector tokens: objects of c vectors of one label, in whole numbers."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "mv_id long, tok_ix int, vec array<double>"


class Label(InputPartition):
    def __init__(self, label: int):
        super().__init__(label)


class Reader(DataSourceReader):
    """One partition a label; a partition reads the rows of its label alone, by a filter pushed into the file."""

    def __init__(self, options):
        self.path, self.c = options["path"], int(options.get("c", "8"))

    def partitions(self):
        import pyarrow.compute as pc
        import pyarrow.dataset as ds

        labels = ds.dataset(self.path).to_table(columns=["label"]).column("label")
        return [Label(x) for x in sorted(pc.unique(labels).to_pylist(), key=lambda x: (x is None, x)) if x is not None]

    def read(self, partition):
        import numpy as np
        import pyarrow.dataset as ds

        rows = ds.dataset(self.path).to_table(columns=["vec_id", "embedding"], filter=ds.field("label") == partition.value).sort_by("vec_id")
        n = len(rows)
        for i, v in enumerate(rows.column("embedding").to_pylist()):
            if i // self.c == (n - 1) // self.c and n % self.c == 1:
                continue  # an object of one token
            yield partition.value * 1_000_000 + i // self.c, i % self.c, [float(x) for x in np.floor(np.array(v, np.float64) * 127 + 0.5)]


class MultiVector(DataSource):
    @classmethod
    def name(cls) -> str:
        return "multivector"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> Reader:
        return Reader(self.options)


def register(spark: SparkSession) -> None:
    """Make ``spark.read.format('multivector')`` known; options: path of embeddings, c tokens an object."""
    spark.dataSource.register(MultiVector)
