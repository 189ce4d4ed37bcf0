"""``spark.read.format("pointtree")``: a store as a data source whose filters prune shards before they are read.

Option ``path`` names the store's folder as a URI that pyarrow's file systems open. Columns are x, y, z and the attributes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.dataset as ds
from pyarrow import fs
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructType

from ..operators import shards as kernel


def _open(path: str, name: str) -> ds.Dataset:
    system, inner = fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)
    return ds.dataset(f"{inner}/{name}", filesystem=system, format="parquet")


class Shard(InputPartition):
    def __init__(self, shard: str):
        self.shard = shard


class PointTreeSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "pointtree"

    def _attributes(self) -> list[str]:
        return _open(self.options["path"], "manifest").to_table(columns=["attributes"]).column(0)[0].as_py()

    def schema(self) -> str:
        return "x long, y long, z long" + "".join(f", {a} int" for a in self._attributes())

    def reader(self, schema: StructType) -> DataSourceReader:
        return PointTreeReader(self.options["path"], [f.name for f in schema.fields])


class PointTreeReader(DataSourceReader):
    def __init__(self, path: str, names: list[str]):
        self.path, self.names = path, names
        self.bounds: dict[str, list[float]] = {}

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        """Comparisons with a constant bound their column; Spark tests them again, since attributes may be null."""
        for f in filters:
            column, value = getattr(f, "attribute", (None,)), getattr(f, "value", None)
            if len(column) == 1 and column[0] in self.names and isinstance(value, int):
                b = self.bounds.setdefault(column[0], [-np.inf, np.inf])
                if isinstance(f, (GreaterThan, GreaterThanOrEqual, EqualTo)):
                    b[0] = max(b[0], value)
                if isinstance(f, (LessThan, LessThanOrEqual, EqualTo)):
                    b[1] = min(b[1], value)
            yield f

    def partitions(self) -> list[InputPartition]:
        shards, keep = _open(self.path, "shards"), None
        for c, (lo, hi) in self.bounds.items():
            cond = (ds.field(f"{c}_max") >= lo) & (ds.field(f"{c}_min") <= hi)
            keep = cond if keep is None else keep & cond
        return [Shard(s) for s in shards.to_table(columns=["shard"], filter=keep).column(0).to_pylist()]

    def read(self, partition: Shard) -> Iterator[pa.RecordBatch]:
        attributes = [n for n in self.names if n not in "xyz"]
        columns = ["level", "x0", "y0", "z0", "side", "parts", "leaf_order", "root_leaf", *kernel.FIELDS, *[f"a_{a}" for a in attributes]]
        for row in _open(self.path, "shards").to_table(columns=columns, filter=ds.field("shard") == partition.shard).to_pylist():
            box = []
            for end in (0, 1):
                for a in "xyz":
                    lo, hi = self.bounds.get(a, (-np.inf, np.inf))
                    box.append(int(max(lo - row[f"{a}0"], 0)) if end == 0 else int(min(hi - row[f"{a}0"], row["side"] - 1)))
            got = kernel.scan(kernel.from_row(row), tuple(box), columns=attributes)
            arrays = []
            for n in self.names:
                v = got[n] + row[f"{n}0"] if n in "xyz" else got[n]
                arrays.append(pa.array(v, pa.int64()) if n in "xyz" else pa.array(np.nan_to_num(v).astype(np.int32), pa.int32(), mask=np.isnan(v) if v.dtype.kind == "f" else None))
            yield pa.RecordBatch.from_arrays(arrays, names=self.names)
