"""Joining what two systems hold: node tables of two indexes with the same splits, and small-group vector means."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F


def merge_nodes(a: DataFrame, b: DataFrame) -> DataFrame:
    """(code, n, ssum, sq): additive statistics of two node tables, met by code in a cogroup; a code may be in one alone."""

    def both(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        rows = pd.concat([x, y])
        return pd.DataFrame({"code": [rows["code"].iloc[0]], "n": [int(rows["n"].sum())], "ssum": [np.sum(np.stack(rows["ssum"].to_list()), axis=0).tolist()], "sq": [float(rows["sq"].sum())]})

    columns = ["code", "n", "ssum", "sq"]
    return a.select(*columns).groupBy("code").cogroup(b.select(*columns).groupBy("code")).applyInPandas(both, "code string, n long, ssum array<double>, sq double")


def group_means(df: DataFrame, by: str) -> DataFrame:
    """Mean vector of each group by a grouped-aggregate UDF: for groups that fit a task; large ones take sums by dimension."""

    @F.pandas_udf("array<double>")
    def mean(v: pd.Series) -> list[float]:
        return np.mean(np.stack(v.to_list()), axis=0).tolist()

    return df.groupBy(by).agg(mean(F.transform("v", lambda x: x.cast("double"))).alias("mean"))
