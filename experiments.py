"""Run every experiment on this machine and print its table: python experiments.py [data folder]."""

from __future__ import annotations

import os
import sys

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from callweave.micro.experiments import run_all
    from callweave.session import LOCAL, build_session

    spark = build_session("local[8]", {**LOCAL, "spark.driver.memory": "6g"}, "experiments")
    spark.sparkContext.setLogLevel("ERROR")
    for name, table in run_all(spark, sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1").items():
        print(f"\n{name}")
        table.show(40, truncate=False)
    spark.stop()


if __name__ == "__main__":
    main()
