"""python -m batchfeed list | run QUERY... --data DIR [--out DIR] | sql TEXT --data DIR"""

from __future__ import annotations

import argparse
import os


def main(argv: list[str] | None = None) -> int:
    p = argparse.ArgumentParser(prog="batchfeed")
    sub = p.add_subparsers(dest="what", required=True)
    sub.add_parser("list", help="names of the queries, those with an oracle marked")
    run = sub.add_parser("run", help="run queries and show or write their results")
    run.add_argument("names", nargs="+")
    text = sub.add_parser("sql", help="a query over the feed_* views")
    text.add_argument("text")
    for x in (run, text):
        x.add_argument("--data", required=True, help="folder with the tables")
        x.add_argument("--out", help="folder for Parquet results; else the first rows are shown")
        x.add_argument("--rows", type=int, default=20)
    a = p.parse_args(argv)
    from .plans.catalog import ORACLES, QUERIES

    if a.what == "list":
        print("\n".join(f"{n}{' *' if n in ORACLES else ''}" for n in sorted(QUERIES)))
        return 0
    from pyspark.sql import SparkSession

    from .api import Engine
    from .session import local_session

    spark = SparkSession.getActiveSession() or local_session(int(os.environ.get("BENCH_CPUS", "8")))
    engine = Engine(spark, a.data)
    for name, df in [(n, engine.query(n)) for n in a.names] if a.what == "run" else [("sql", engine.sql(a.text))]:
        df.write.mode("overwrite").parquet(f"{a.out}/{name}") if a.out else df.show(a.rows, truncate=False)
    return 0


if __name__ == "__main__":
    raise SystemExit(main())
