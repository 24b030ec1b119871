"""SQL functions on stored summaries: summary_quantile, summary_rank, summary_size, summary_merge, phi_grid, quantile_gap."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from rankspark import shipping, synopsis
from rankspark.params import MethodSpec


def register(spark: SparkSession) -> None:
    shipping.ensure(spark)

    @F.pandas_udf("double")
    def summary_quantile(payload: pd.Series, num: pd.Series, den: pd.Series) -> pd.Series:
        return pd.Series([None if p is None else synopsis.unpack(p).query([(int(a), int(b))])[0] for p, a, b in zip(payload, num, den, strict=True)], dtype="float64")

    @F.pandas_udf("long")
    def summary_rank(payload: pd.Series, x: pd.Series) -> pd.Series:
        """The middle of the bounds of the number of values <= x."""
        return pd.Series([sum(synopsis.unpack(p).rank(v)) // 2 for p, v in zip(payload, x, strict=True)], dtype="int64")

    @F.pandas_udf("long")
    def summary_size(payload: pd.Series) -> pd.Series:
        return pd.Series([len(synopsis.unpack(p)) for p in payload], dtype="int64")

    @F.pandas_udf("binary")
    def summary_merge(payload: pd.Series) -> bytes:
        """Only summaries are shuffled to it."""
        first = None
        for p in payload:
            s = synopsis.unpack(p)
            first = s if first is None else (first.merge(s) or first)
        return first.pack() if first is not None else b""

    @F.pandas_udf("double")
    def quantile_gap(v: pd.Series, eps: pd.Series, num: pd.Series, den: pd.Series) -> float:
        """For small groups: raw rows are shuffled to it, without partial aggregation."""
        s = synopsis.new(MethodSpec.of("gap", str(eps.iloc[0])))
        s.absorb(v.dropna().to_numpy())
        return s.query([(int(num.iloc[0]), int(den.iloc[0]))])[0]

    @F.udtf(returnType="phi_num int, phi_den int")
    class PhiGrid:
        def eval(self, den: int):
            for k in range(1, den):
                yield k, den

    for name, f in (("summary_quantile", summary_quantile), ("summary_rank", summary_rank), ("summary_size", summary_size), ("summary_merge", summary_merge), ("quantile_gap", quantile_gap)):
        spark.udf.register(name, f)
    spark.udtf.register("phi_grid", PhiGrid)
