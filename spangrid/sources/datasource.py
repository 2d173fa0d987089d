"""A saved grid as a data source: pushed comparisons prune pages before a file is opened."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

_NAMES = {"t_lo", "t_hi", "dur"}


class GridSource(DataSource):
    """spark.read.format("interval_grid").option("pages", <json of the directory>).load(path)"""

    @classmethod
    def name(cls) -> str:
        return "interval_grid"

    def schema(self) -> str:
        return "iv_id long, t_lo long, t_hi long, dur long"

    def reader(self, schema) -> DataSourceReader:
        return GridReader(self.options)


class GridReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.pages, self.limits = options["path"], json.loads(options["pages"]), []

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        """Keeps comparisons with the interval columns for pruning; all are still tested on the rows."""
        for f in filters:
            if isinstance(f, (EqualTo, GreaterThan, GreaterThanOrEqual, LessThan, LessThanOrEqual)) and len(f.attribute) == 1 and f.attribute[0] in _NAMES:
                self.limits.append((type(f).__name__, f.attribute[0], f.value))
            yield f

    def _may(self, page: dict) -> bool:
        key = {"t_lo": "lo", "t_hi": "hi", "dur": "dur"}
        for op, name, v in self.limits:
            low, top = page[f"min_{key[name]}"], page[f"max_{key[name]}"]
            if (op == "EqualTo" and not low <= v <= top) or (op == "GreaterThan" and top <= v) or (op == "GreaterThanOrEqual" and top < v) or (op == "LessThan" and low >= v) or (op == "LessThanOrEqual" and low > v):
                return False
        return True

    def partitions(self) -> list[InputPartition]:
        by_column: dict[int, list[int]] = {}
        for page in self.pages:
            if self._may(page):
                by_column.setdefault(page["col_id"], []).append(page["cell_id"])
        return [InputPartition((c, cells)) for c, cells in sorted(by_column.items())] or [InputPartition((None, []))]

    def read(self, partition: InputPartition):
        import pyarrow.dataset as ds

        column, cells = partition.value
        if column is None:
            return
        data = ds.dataset(f"{self.path}/rows/col_id={column}", format="parquet")
        yield from data.scanner(columns=["iv_id", "t_lo", "t_hi", "dur"], filter=ds.field("cell_id").isin(cells)).to_batches()


def read_grid(spark: SparkSession, path: str):
    """The rows of a grid saved at a path that workers can open (for other stores use open_grid and its scans)."""
    spark.dataSource.register(GridSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    pages = [r.asDict() for r in spark.read.parquet(f"{path}/pages").drop("heavy").collect()]  # the directory
    local = path.removeprefix("file://")
    return spark.read.format("interval_grid").option("pages", json.dumps(pages)).load(local)
