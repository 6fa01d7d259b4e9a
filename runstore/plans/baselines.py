"""What run tables are measured against: rows, pruned columns, vertical partitions, indexes, the read-only floor."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from runstore.catalog import SCHEMAS
from runstore.operators import positions, runs
from runstore.plans import collapse, rewrite
from runstore.plans.views import answer
from runstore.sources import layout
from runstore.spec import Pred, SortedProjection, StarQuery, joined


def to_row_layout(catalog, table: str) -> str:
    """The table with each tuple as one serialized value, in primary-key order: nothing can be pruned."""
    def build() -> str:
        path = catalog.path(f"rows-{table}")
        df = catalog.table(table)
        key = df.columns[0]
        df.repartitionByRange(key).sortWithinPartitions(key).select(F.to_json(F.struct("*")).alias("tuple")).write.parquet(path)
        return path

    return catalog.made(("row layout", table), build)


class RowCatalog:
    """A catalog whose tables are read from the row layout."""

    def __init__(self, catalog):
        self.catalog, self.spark = catalog, catalog.spark

    def table(self, name: str) -> DataFrame:
        df = self.spark.read.schema("tuple string").parquet(to_row_layout(self.catalog, name))
        return df.select(F.from_json("tuple", SCHEMAS[name]).alias("t")).select("t.*")


def scan_rows(catalog, table: str) -> DataFrame:
    return RowCatalog(catalog).table(table)


def run_row(catalog, q: StarQuery) -> DataFrame:
    """The traditional plan over whole serialized tuples."""
    return answer(joined(RowCatalog(catalog), q.base, q.joins), q)


def run_columnar(catalog, q: StarQuery) -> DataFrame:
    """The traditional plan over column-pruned Parquet."""
    return answer(joined(catalog, q.base, q.joins), q)


def _placed(catalog, p: SortedProjection) -> DataFrame:
    """The joined rows with a row id, the carrier of vertical partitions and indexes."""
    def build() -> DataFrame:
        cols = list(p.sort_cols)
        rows = p.frame(catalog).select(*cols)
        return catalog.stored(positions.assign_positions(catalog, rows, cols[::-1]).withColumnRenamed("pos", "rid"), f"{p.name}-placed")

    return catalog.made(("placed", p), build)


def build_vertical(catalog, p: SortedProjection) -> dict[str, DataFrame]:
    """One (rid, v) table for each column, ordered by row id, not compressed by runs."""
    def part(c: str) -> DataFrame:
        df = _placed(catalog, p).select("rid", F.col(c).alias("v"))
        return catalog.stored(df.repartitionByRange("rid").sortWithinPartitions("rid"), f"{p.name}-vertical-{c}")

    return catalog.made(("vertical", p), lambda: {c: part(c) for c in p.sort_cols})


def build_index(catalog, p: SortedProjection) -> dict[str, DataFrame]:
    """One (v, rid) table for each column, ordered by value."""
    def part(c: str) -> DataFrame:
        df = _placed(catalog, p).select(F.col(c).alias("v"), "rid")
        return catalog.stored(df.repartitionByRange("v", "rid").sortWithinPartitions("v", "rid"), f"{p.name}-index-{c}")

    return catalog.made(("index", p), lambda: {c: part(c) for c in p.sort_cols})


def _by_row_id(tables: dict[str, DataFrame], q: StarQuery, p: SortedProjection) -> DataFrame:
    frames = []
    for c in rewrite.needed_columns(p, q):
        df = tables[c]
        for x in q.preds:
            if x.col == c:
                df = df.where(x.on(F.col("v")))
        frames.append(df.select("rid", F.col("v").alias(c)))
    rows = reduce(lambda a, b: a.join(b.hint("merge"), "rid"), frames)
    return answer(rows, StarQuery(q.base, q.joins, (), q.columns, q.aggs, q.order, q.limit))


def run_vertical(catalog, q: StarQuery, p: SortedProjection) -> DataFrame:
    return _by_row_id(build_vertical(catalog, p), q, p)


def run_index(catalog, q: StarQuery, p: SortedProjection) -> DataFrame:
    return _by_row_id(build_index(catalog, p), q, p)


def run_hybrid(catalog, q: StarQuery, p: SortedProjection, key: str) -> DataFrame:
    """Comparisons on the projection's columns answered from runs, the rest on base rows.

    The runs give the values of `key` that can qualify (a semi-join, not the
    answer); base rows decide.
    """
    known = tuple(x for x in q.preds if x.col in p.sort_cols)
    got = rewrite.positions_of(catalog, StarQuery(q.base, q.joins, known, (key,)), p)
    rows = joined(catalog, q.base, q.joins)
    if got is None:  # a collapsed span is empty
        return answer(rows.where("false"), q)
    hits = got[0].select(F.col(key).alias("_key")).distinct()
    return answer(rows.join(hits, rows[key].eqNullSafe(hits["_key"]), "left_semi"), q)


def drain(df: DataFrame) -> None:
    """Run a frame to its end without keeping anything."""
    df.write.format("noop").mode("overwrite").save()


def floor_scan(catalog, q: StarQuery, p: SortedProjection) -> list[DataFrame]:
    """Only the reads that any column plan must do: needed columns, within the span the sort confines."""
    tables = runs.build_runs(catalog, p)
    span, out, confined = None, [], True
    for c in rewrite.needed_columns(p, q):
        mine: tuple[Pred, ...] = tuple(x for x in q.preds if x.col == c)
        confined = confined and bool(mine) and all(x.contiguous for x in mine) and all(any(y.col == d and y.op == "=" for y in q.preds) for d in p.sort_cols[: p.depth(c) - 1])
        if confined:
            span = collapse.collapse_span(catalog, tables[c], mine, span)
            if span is None:
                return out
            out.append(layout.read_by_value(catalog, tables[c], mine))
        else:
            out.append(layout.read_runs(tables[c], span))
    return out


def floor_time(catalog, q: StarQuery, p: SortedProjection) -> float:
    """Seconds to read them."""
    import time

    frames = floor_scan(catalog, q, p)
    began = time.perf_counter()
    for df in frames:
        drain(df)
    return time.perf_counter() - began
