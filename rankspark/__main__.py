"""Quantiles of one column from the command line."""

from __future__ import annotations

import argparse

from pyspark.sql import SparkSession

from rankspark import engine
from rankspark.params import GRID
from rankspark.synopsis import KINDS


def main() -> None:
    ask = argparse.ArgumentParser(prog="rankspark")
    ask.add_argument("--table", required=True, help="a Parquet path")
    ask.add_argument("--column", required=True)
    ask.add_argument("--by", nargs="*", default=[])
    ask.add_argument("--eps", default="0.01")
    ask.add_argument("--method", default="gap", choices=sorted(KINDS))
    a = ask.parse_args()
    spark = SparkSession.builder.appName("rankspark").getOrCreate()
    told = engine.quantiles(spark.read.parquet(a.table), a.column, GRID, a.eps, a.method, a.by)
    told.orderBy(*a.by, "phi_num").show(1000, truncate=False)  # one screen of answers


if __name__ == "__main__":
    main()
