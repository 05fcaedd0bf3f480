"""Costs of the variants against their baselines, by the metrics of the plans that ran. python -m skyjoin.experiments [folder ...]"""

from __future__ import annotations

import os
import sys

from pyspark.sql import DataFrame, SparkSession

from .operators.match import Participant, match_all
from .operators.metrics import measured
from .operators.regions import parse_region
from .operators.zones import Grid
from .plans import planner
from .sources.catalogs import ZoneCache
from .sources.skyfix import catalog

FIELDS = ("rows", "seconds", "shuffle_bytes", "shuffle_rows", "scan_bytes", "scan_rows")
LIMIT = 1e6


def _parts(spark: SparkSession, d: str, columns: tuple[str, ...] = ()) -> list[Participant]:
    return [Participant(n, catalog(spark, d, n), error=e, columns=columns) for n, e in (("optical", 0.1), ("uv", 0.2))]


def variants(spark: SparkSession, d: str) -> dict[tuple[str, str], DataFrame]:
    """(experiment, variant) to the query that stands for it."""
    wide, narrow, region, grid = _parts(spark, d, ("mag", "ra", "dec", "obj")), _parts(spark, d), parse_region("circle J2000 180 0 60"), Grid(30.0 / 3600)
    owner = [Participant("optical", narrow[0].df, error=0.1, columns=("ra", "dec")), narrow[1]]
    kept = ZoneCache(spark, buckets=8).get_or_build("uv", d, narrow[1].df.select("key", "ra", "dec"), ("ra", "dec"), grid)
    return {
        ("payload", "carry"): match_all(wide, LIMIT),
        ("payload", "rejoin"): match_all(wide, LIMIT, payload="rejoin"),
        ("region", "owner"): match_all(owner, LIMIT, region=region),
        ("region", "post"): match_all(owner, LIMIT, region=region, region_on="post"),
        ("zone cache", "none"): match_all(narrow, LIMIT, grid=grid),
        ("zone cache", "bucketed"): match_all([narrow[0], Participant("uv", kept, error=0.2, grid=grid)], LIMIT),
        ("partitions", "1 wedge"): planner.execute(narrow, LIMIT, "wedges", rate=1.0, n=1),
        ("partitions", "8 wedges"): planner.execute(narrow, LIMIT, "wedges", rate=1.0, n=8),
        ("partitions", "one join"): planner.execute(narrow, LIMIT, "join", rate=1.0),
    }


def costs(spark: SparkSession, d: str) -> list[tuple]:
    """A row for each variant: experiment, variant and the FIELDS of its run, with joins that shuffle, as at sizes beyond a broadcast."""
    name = "spark.sql.autoBroadcastJoinThreshold"
    before = spark.conf.get(name)
    spark.conf.set(name, "-1")
    try:
        return [(*k, *(float(m[f]) for f in FIELDS)) for k, df in variants(spark, d).items() for m in [measured(df)]]
    finally:
        spark.conf.set(name, before)


def main() -> None:
    spark = SparkSession.builder.master(os.environ.get("BENCH_MASTER", "local[8]")).config("spark.sql.shuffle.partitions", "16").config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for d in sys.argv[1:] or ["/root/testdata/sf0.01"]:
        match_all(_parts(spark, d), LIMIT).count()  # warm
        print(f"{d}\n| experiment | variant | {' | '.join(FIELDS)} |")
        for row in costs(spark, d):
            print(f"| {row[0]} | {row[1]} | " + " | ".join(f"{x:.2f}" if f == "seconds" else f"{x:.0f}" for f, x in zip(FIELDS, row[2:], strict=True)) + " |")


if __name__ == "__main__":
    main()
