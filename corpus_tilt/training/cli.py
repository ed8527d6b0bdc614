"""Command line: ``python -m corpus_tilt.training.cli run --task lang_fr --method implicit --data DIR``."""

from __future__ import annotations

import argparse

from pyspark.sql import SparkSession

from .bilevel import METHODS
from .experiments import EXPERIMENTS, compare


def main(argv: list[str] | None = None) -> None:
    parser = argparse.ArgumentParser(description=__doc__)
    sub = parser.add_subparsers(dest="what", required=True)
    run = sub.add_parser("run", help="one method, or all, on one task")
    run.add_argument("--task", required=True)
    run.add_argument("--method", choices=[*METHODS, "all"], default="all")
    exp = sub.add_parser("experiment", help="a whole experiment")
    exp.add_argument("name", choices=list(EXPERIMENTS))
    for p in (run, exp):
        p.add_argument("--data", required=True, help="folder of Parquet tables")
    args = parser.parse_args(argv)
    spark = SparkSession.builder.appName("corpus_tilt").getOrCreate()
    if args.what == "run":
        methods = tuple(METHODS) if args.method == "all" else (args.method,)
        for row in compare(spark, args.data, args.task, methods):
            print(*row)
    else:
        EXPERIMENTS[args.name](spark, args.data).show(500, truncate=False)


if __name__ == "__main__":
    main()
