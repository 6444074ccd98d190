"""python -m stepsql NAME [DIR] runs a query and shows its first rows; without a name it lists them."""

from __future__ import annotations

import sys

from pyspark.sql import SparkSession


def main() -> None:
    from stepsql.queries import QUERIES

    if len(sys.argv) < 2:
        print("\n".join(sorted(QUERIES)))
        return
    spark = SparkSession.builder.appName("stepsql").getOrCreate()
    QUERIES[sys.argv[1]](spark, sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.01").show(20, truncate=80)


if __name__ == "__main__":
    main()
