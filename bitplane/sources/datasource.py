"""A Python data source over encoded datasets: SQL filters on values become predicates on planes."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, In, InputPartition, IsNotNull, LessThan, LessThanOrEqual

from ..plans import binding, kernels, predicates
from ..plans.spec import Manifest


class SlicedDataSource(DataSource):
    """Options: files (comma-separated word files), manifest (JSON).  Reads columns as BIGINT ordinals.

    A loaded frame keeps the filters first pushed into it: load anew for each query.
    """

    @classmethod
    def name(cls) -> str:
        return "sliced"

    def schema(self) -> str:
        return ", ".join(f"{c.name} bigint" for c in Manifest.from_json(self.options["manifest"]).columns)

    def reader(self, schema) -> DataSourceReader:
        return SlicedReader(self.options)


class FilePart(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class SlicedReader(DataSourceReader):
    def __init__(self, options):
        self.files, self.manifest_text, self.node = options["files"].split(","), options["manifest"], ("and", [])

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Takes what planes decide; gives back the rest."""
        manifest, parts = Manifest.from_json(self.manifest_text), []
        for f in filters:
            p = to_pred(f, manifest)
            if p is None:
                yield f
            else:
                parts.append(binding.bind(p, manifest))
        self.node = binding.both(*parts) if parts else ("and", [])

    def partitions(self) -> list[FilePart]:
        return [FilePart(p) for p in self.files]

    def read(self, part: FilePart):
        import numpy as np
        import pyarrow as pa
        import pyarrow.parquet as pq

        manifest = Manifest.from_json(self.manifest_text)
        for batch in pq.ParquetFile(part.path.removeprefix("file://")).iter_batches():
            def column(name: str, batch=batch):
                a = batch.column(batch.schema.get_field_index(name))
                if name.endswith("__v"):
                    return None if a.null_count == len(a) else a.fill_null(-1).to_numpy(zero_copy_only=False)
                return a.fill_null(0).to_numpy(zero_copy_only=False)

            mask = column("live") if self.node == ("and", []) else kernels.numpy_mask(self.node, manifest, column)
            rows, pos = np.nonzero(np.unpackbits(np.ascontiguousarray(mask).view(np.uint8), bitorder="little").reshape(-1, 64))
            cols = []
            for s in manifest.columns:
                x = np.zeros(len(rows), np.uint64)
                for j in range(s.planes):
                    x |= (column(s.plane(j)).view(np.uint64)[rows] >> pos.astype(np.uint64) & np.uint64(1)) << np.uint64(j)
                base = np.full(len(rows), s.base) if s.literal else column(s.header("bias"))[rows]
                v = column(s.header("v"))
                gone = None if v is None else (v.view(np.uint64)[rows] >> pos.astype(np.uint64) & np.uint64(1)) == 0
                cols.append(pa.array((x + base.astype(np.int64).view(np.uint64)).view(np.int64), mask=gone))
            yield pa.RecordBatch.from_arrays(cols, [s.name for s in manifest.columns])


def to_pred(f: Filter, manifest: Manifest) -> predicates.Pred | None:
    if len(getattr(f, "attribute", ())) != 1 or f.attribute[0] not in manifest:
        return None
    col = f.attribute[0]
    ops = {EqualTo: "eq", GreaterThan: "gt", GreaterThanOrEqual: "ge", LessThan: "lt", LessThanOrEqual: "le"}
    if type(f) in ops:
        return predicates.Cmp(ops[type(f)], col, f.value)
    if isinstance(f, In):
        return predicates.in_list(col, f.value)
    return predicates.not_null(col) if isinstance(f, IsNotNull) else None
