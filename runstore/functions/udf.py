"""The slow paths that native forms are compared with: a grouped run-length encoder and table functions over runs."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def rle_encode(rows: DataFrame, group: str, order: str, value: str) -> DataFrame:
    """Runs (group, f, v, c) of an ordered group, in pandas: the group is held in memory."""
    kind = dict(rows.dtypes)

    def encode(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(order, ignore_index=True)
        same = pdf[value].eq(pdf[value].shift()) | (pdf[value].isna() & pdf[value].shift().isna() & (pdf.index > 0))
        run = (~same).cumsum()
        got = pdf.groupby(run, sort=True).agg(v=(value, "first"), c=(value, "size")).reset_index(drop=True)
        got["f"] = got["c"].cumsum() - got["c"] + 1
        got[group] = key[0]
        return got[[group, "f", "v", "c"]]

    return rows.groupBy(group).applyInPandas(encode, f"{group} {kind[group]}, f long, v {kind[value]}, c long")


@F.udtf(returnType="pos: bigint")
class ExpandRun:
    """One row for each position of a run."""

    def eval(self, f: int, c: int) -> Iterator[tuple[int]]:
        for pos in range(f, f + c):
            yield (pos,)


def expand_run(runs: DataFrame) -> DataFrame:
    """(pos, v) by a lateral join with the table function."""
    return runs.lateralJoin(ExpandRun(F.col("f").outer(), F.col("c").outer())).select("pos", "v")
