"""Tables from which the rows of a few keys are read, and little else."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows of a page, the least that is read for a key.
PAGE_ROWS = 128


class Lookup:
    """A table as Parquet: a folder per partition label, sorted by key, in small
    pages with an index of their keys.  A list of keys prunes folders, row groups
    and pages, so a read costs about a page a key, not the table."""

    def __init__(self, df: DataFrame, key: str, path: str):
        self.key, self.path, self.spark = key, path, df.sparkSession
        df.sortWithinPartitions("pid", key).write.partitionBy("pid").option("parquet.page.row.count.limit", PAGE_ROWS).option("parquet.page.size.row.check.min", PAGE_ROWS).option("compression", "zstd").parquet(path)
        self._table = self.spark.read.schema(df.schema).parquet(path).select(df.columns)

    def rows(self, pids: list[int], keys: list[int]) -> DataFrame:
        """The rows with one of these keys, all of which lie in these partitions."""
        return self._table.where(F.col("pid").isin(*sorted(set(pids))) & F.col(self.key).isin(*sorted(set(keys))))


def rows_scanned(df: DataFrame) -> int:
    """Rows that the scans of an executed plan gave out."""
    total, todo = 0, [df._jdf.queryExecution().executedPlan()]
    while todo:
        node = todo.pop()
        children = node.children()
        todo += [children.apply(i) for i in range(children.size())]
        if "FileSourceScan" in node.getClass().getSimpleName():
            total += node.metrics().apply("numOutputRows").value()
    return total
