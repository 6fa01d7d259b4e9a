"""Tables with pinned schemas, scratch space, and the projections and views built in a session."""

from __future__ import annotations

import atexit
import json
import time
import uuid
from collections.abc import Callable
from typing import Any

from pyspark.sql import DataFrame, SparkSession

# The given tables' schemas; time stamps carry no zone.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn int, role string, text string",
}


#: Files of a table are looked at again after so many seconds.
LOOK_SECONDS = 10.0

_scratch: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's `spark.checkpoint.dir`, else the context's checkpoint folder.

    A local one is taken only where all runs on one machine.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = held.get() if held.isDefined() else None
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        root = "file:///tmp/checkpoints/runstore"
    return root.rstrip("/")


def scratch_folder(spark: SparkSession, name: str) -> str:
    """A new folder below the shared one; it goes when the program ends, or with `clean`."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    if not _scratch:
        atexit.register(clean)
    _scratch.append((spark, path))
    return path


def file_system(spark: SparkSession, path: str):
    """Spark's own view of a path: (file system, path)."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), at


def clean() -> None:
    """Delete all scratch folders of this program; frames that read them end with it."""
    while _scratch:
        spark, path = _scratch.pop()
        try:
            fs, at = file_system(spark, path)
            fs.delete(at, True)
        except Exception:  # the session's Java side is gone: nothing can be deleted any more
            _scratch.clear()


def stored_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of the files below a path."""
    fs, at = file_system(spark, path)
    return fs.getContentSummary(at).getLength()


class Catalog:
    """One data folder in one session."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir, self._made = spark, sf_dir, {}
        self.root = scratch_folder(spark, "catalog")
        #: Number of times each table was replaced.
        self.versions: dict[str, int] = {}
        self._tables: dict[str, DataFrame] = {}
        self._listed: dict[str, tuple[float, tuple]] = {}

    def table(self, name: str) -> DataFrame:
        if name in self._tables:
            return self._tables[name]
        return self.spark.read.schema(SCHEMAS[name]).parquet(f"{self.sf_dir}/{name}.parquet")

    def replace(self, name: str, rows: DataFrame) -> None:
        """Let a table be these (stored) rows from now on; what was made of the old ones is made anew when asked for."""
        self._tables[name] = rows
        self.versions[name] = self.versions.get(name, 0) + 1

    def signature(self, tables: tuple[str, ...]) -> tuple:
        """What changes when one of the tables does: its number of replacements, its files' lengths and times."""
        return tuple((name, self.versions.get(name, 0), self._files(name) if name in SCHEMAS and name not in self._tables else ()) for name in tables)

    def _files(self, name: str) -> tuple:
        """(name, length, time) of a table's files; listed again after `LOOK_SECONDS`."""
        seen = self._listed.get(name)
        if seen is None or time.monotonic() - seen[0] > LOOK_SECONDS:
            fs, at = file_system(self.spark, f"{self.sf_dir}/{name}.parquet")
            files = tuple(sorted((f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in fs.listStatus(at))) if fs.exists(at) else ()
            seen = self._listed[name] = (time.monotonic(), files)
        return seen[1]

    def made(self, key: Any, build: Callable[[], Any]) -> Any:
        """What build gives, made once as long as the tables it is made of do not change.

        Tables are known for keys that hold their names, a projection, a query or a view definition.
        """
        now = self.signature(tuple(t for x in key for t in ((x.base, *[j.table for j in x.joins]) if hasattr(x, "joins") else (x,) if x in SCHEMAS else ()))) if isinstance(key, tuple) else ()
        if key not in self._made or self._made[key][0] != now:
            self._made[key] = (now, build())
        return self._made[key][1]

    def keep(self, key: Any, value: Any, of: Any) -> None:
        """Put a value for a key that was brought up to date by other means than building it."""
        self._made[key] = (self.signature((of.base, *[j.table for j in of.joins])), value)

    def count(self, name: str) -> int:
        """Rows of a table, counted once."""
        return self.made(("count", name), lambda: self.table(name).count())

    def path(self, name: str) -> str:
        """A new place below this catalog's folder in shared scratch space."""
        return f"{self.root}/{name}-{uuid.uuid4().hex[:8]}"

    def stored(self, df: DataFrame, name: str) -> DataFrame:
        path = self.path(name)
        df.write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def load(self, path: str, fmt: str, schema: str, **options: Any) -> DataFrame:
        """Read csv, json, orc or parquet with a stated schema."""
        return self.spark.read.schema(schema).options(**options).format(fmt).load(path)

    def save(self, df: DataFrame, path: str, fmt: str, partition_by: tuple[str, ...] = (), **options: Any) -> None:
        df.write.mode("overwrite").options(**options).partitionBy(*partition_by).format(fmt).save(path)

    def save_manifest(self, name: str, rows: list[dict]) -> str:
        """Write a projection's manifest beside its run tables, as JSON lines."""
        path = self.path(f"{name}-manifest")
        self.spark.createDataFrame([(json.dumps(r),) for r in rows], "value string").coalesce(1).write.text(path)
        return path


_catalogs: dict[tuple[str, str], Catalog] = {}


def catalog(spark: SparkSession, sf_dir: str) -> Catalog:
    """This session's catalog of a folder: run tables and views are built once."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _catalogs:
        _catalogs[key] = Catalog(spark, sf_dir)
    return _catalogs[key]
