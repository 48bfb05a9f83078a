"""One launch path for local and cluster runs: ``python -m trajkit.cli loss_window --data DIR`` or the same file under spark-submit."""

from __future__ import annotations

import argparse
import json
from dataclasses import fields

from trajkit.pipeline import Config


LOOPS = ("train_loop", "wl_full_path")  # queries that run the training loop, and so take its settings


def config(path: str | None) -> Config:
    """The run's configuration from a JSON file, checked; unknown names fail."""
    given = {}
    if path:
        with open(path) as f:
            given = json.load(f)
    unknown = set(given) - {f.name for f in fields(Config)}
    if unknown:
        raise ValueError(f"unknown settings: {sorted(unknown)}")
    return Config(**given).check()


def main(args: list[str] | None = None) -> int:
    parser = argparse.ArgumentParser(prog="trajkit")
    parser.add_argument("query", help="a registered query, or 'list'")
    parser.add_argument("--data", default="/root/testdata/sf0.001", help="folder of the tables")
    parser.add_argument("--out", help="write the result there as Parquet instead of showing it")
    parser.add_argument("--config", help="JSON file with settings of the training loop")
    parser.add_argument("--master", help="for local runs, e.g. local[4]; leave out under spark-submit")
    a = parser.parse_args(args)
    settings = config(a.config)
    from trajkit import catalog

    if a.query == "list":
        print("\n".join(sorted(catalog.QUERIES)))
        return 0
    if a.query not in catalog.QUERIES:
        parser.error(f"no query {a.query}")
    if a.config and a.query not in LOOPS:
        parser.error(f"--config is for {', '.join(LOOPS)}")
    from pyspark.sql import SparkSession

    builder = SparkSession.builder.appName("trajkit")
    spark = (builder.master(a.master) if a.master else builder).getOrCreate()
    df = catalog.QUERIES[a.query](spark, a.data, *([settings] if a.config else []))
    df.write.mode("overwrite").parquet(a.out) if a.out else df.show(20, truncate=False)
    return 0


if __name__ == "__main__":
    raise SystemExit(main())
