"""`spark.read.format('runstore')`: run tables as a data source with pushed comparisons on f and v."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

_PYARROW = {EqualTo: "==", GreaterThan: ">", GreaterThanOrEqual: ">=", LessThan: "<", LessThanOrEqual: "<="}


def _file_system(path: str):
    """The Arrow file system of a path or URI (hdfs, s3, gs, file), and the path in it."""
    from pyarrow import fs

    if "://" not in path and not path.startswith("file:"):
        return fs.LocalFileSystem(), path
    return fs.FileSystem.from_uri(path if "://" in path else "file://" + path.removeprefix("file:"))


def _open_folder(path: str):
    """(file system, its Parquet files below the path); an error if there are none."""
    from pyarrow import fs

    system, at = _file_system(path)
    found = sorted(x.path for x in system.get_file_info(fs.FileSelector(at, recursive=False)) if x.base_name.endswith(".parquet"))
    if not found:
        raise FileNotFoundError(f"no run table below {path}")
    return system, found


class FilePart(InputPartition):
    def __init__(self, path: str, group: int):
        self.path, self.group = path, group


class RunStoreReader(DataSourceReader):
    """One task for each row group whose statistics admit the pushed comparisons."""

    def __init__(self, path: str):
        self.path, self.kept = path, []

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if type(f) in _PYARROW and len(f.attribute) == 1 and f.attribute[0] in ("f", "v", "c"):
                self.kept.append((f.attribute[0], _PYARROW[type(f)], f.value))
            else:
                yield f

    def _may(self, meta, names: list[str]) -> bool:
        for col, op, value in self.kept:
            if col not in names:
                continue
            s = meta.column(names.index(col)).statistics
            if s is None or not s.has_min_max:
                continue
            try:
                if op in ("==", "<", "<=") and not (s.min < value if op == "<" else s.min <= value):
                    return False
                if op in ("==", ">", ">=") and not (s.max > value if op == ">" else s.max >= value):
                    return False
            except TypeError:
                continue
        return True

    def partitions(self) -> list[FilePart]:
        import pyarrow.parquet as pq

        out = []
        files = _open_folder(self.path)
        for name in files[1]:
            file = pq.ParquetFile(name, filesystem=files[0])
            names = file.schema_arrow.names
            out += [FilePart(name, g) for g in range(file.num_row_groups) if self._may(file.metadata.row_group(g), names)]
        return out or [FilePart("", 0)]

    def read(self, part: FilePart) -> Iterator:
        import pyarrow as pa
        import pyarrow.compute as pc
        import pyarrow.parquet as pq

        if not part.path:
            return
        fs, folder = _file_system(self.path)
        file = pq.ParquetFile(part.path, filesystem=fs)
        t = file.read_row_group(part.group, columns=[c for c in ("f", "v", "c") if c in file.schema_arrow.names])
        if "c" not in t.column_names:
            t = t.append_column("c", pa.array([1] * t.num_rows, pa.int64()))
        compare = {"==": pc.equal, "<": pc.less, "<=": pc.less_equal, ">": pc.greater, ">=": pc.greater_equal}
        for col, op, value in self.kept:
            t = t.filter(compare[op](t[col], pa.scalar(value, t[col].type)))
        yield from t.select(["f", "v", "c"]).to_batches()


class RunStoreSource(DataSource):
    """Options: path (of a written run table, on any store that Arrow opens by its URI) and v (its value's SQL type)."""

    @classmethod
    def name(cls) -> str:
        return "runstore"

    def schema(self) -> str:
        return f"f long, v {self.options['v']}, c long"

    def reader(self, schema) -> RunStoreReader:
        return RunStoreReader(self.options["path"])


def register(spark: SparkSession) -> None:
    """Make the format known; comparisons are pushed only while the session's setting is on."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(RunStoreSource)
