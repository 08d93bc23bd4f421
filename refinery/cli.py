"""python -m refinery.cli run settings.yaml [--dry-run] [--output-dir DIR] [--sync] [--verbose] [--reset-index]"""

from __future__ import annotations

import argparse

from refinery.config import load


def main(args: list[str] | None = None) -> int:
    p = argparse.ArgumentParser(prog="refinery")
    run = p.add_subparsers(dest="command", required=True).add_parser("run")
    run.add_argument("settings")
    run.add_argument("--dry-run", action="store_true")
    run.add_argument("--output-dir")
    run.add_argument("--sync", action="store_true", help="one model call at a time in each task")
    run.add_argument("--verbose", action="store_true")
    run.add_argument("--reset-index", action="store_true")
    given = p.parse_args(args)
    cfg = load(given.settings)
    changes = {"output_dir": given.output_dir} if given.output_dir else {}
    cfg = cfg.patch(changes | {"async_mode": cfg.async_mode and not given.sync, "verbose": given.verbose or cfg.verbose, "reset_index": given.reset_index or cfg.reset_index})
    from refinery.plans import run as plans

    if given.dry_run:
        print(plans.explain(cfg))
        return 0
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.appName("refinery").getOrCreate()
    result = plans.Curation(spark, cfg).run()
    print(result.summary())
    if cfg.verbose:
        print(plans.explain(cfg))
    return 0


if __name__ == "__main__":
    raise SystemExit(main())
