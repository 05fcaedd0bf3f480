"""Cost and accuracy measures, each one aggregate over a match or its parts."""

from __future__ import annotations

import math
import time

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def accuracy(pairs: DataFrame, true: Column, total: int | float) -> DataFrame:
    """found, correct, completeness (of total true pairs), purity and F1."""
    out = pairs.agg(F.count("*").alias("found"), F.coalesce(F.sum(true.cast("long")), F.lit(0)).alias("correct"))
    c, p = F.col("correct") / F.lit(float(total)), F.col("correct") / F.greatest(F.col("found"), F.lit(1))
    return out.withColumns({"completeness": c, "purity": p, "f1": 2 * F.col("correct") / (F.col("found") + F.lit(float(total)))})


def roc(pairs: DataFrame, ln_b: Column, true: Column, limits: list[float]) -> DataFrame:
    """Correct and false pairs above each limit: one pass over the pairs for all limits."""
    sums = [c for k, x in enumerate(limits) for c in (F.sum(((ln_b >= math.log(x)) & true).cast("long")).alias(f"t{k}"), F.sum(((ln_b >= math.log(x)) & ~true).cast("long")).alias(f"f{k}"))]
    rows = F.array(*[F.struct(F.lit(float(x)).alias("evidence"), F.col(f"t{k}").alias("correct"), F.col(f"f{k}").alias("false_pairs")) for k, x in enumerate(limits)])
    return pairs.agg(*sums).select(F.inline(rows))


def calibration(pairs: DataFrame, posterior: str, true: Column, bins: int = 10) -> DataFrame:
    """Mean posterior and share of true pairs in each bin of the posterior."""
    b = F.least(F.lit(bins - 1), F.floor(F.col(posterior) * bins)).cast("int")
    return pairs.groupBy(b.alias("bin")).agg(F.count("*").alias("n"), F.avg(posterior).alias("mean_posterior"), F.avg(true.cast("double")).alias("true_share"))


def balance(df: DataFrame, part: str) -> DataFrame:
    """Rows of the largest part against the mean."""
    return df.groupBy(part).agg(F.count("*").alias("n")).agg(F.count("*").alias("parts"), F.max("n").alias("largest"), F.avg("n").alias("mean"), (F.max("n") / F.avg("n")).alias("max_over_mean"))


def q_error(estimate: float, actual: float) -> float:
    return max(estimate, 1.0) / max(actual, 1.0) if estimate > actual else max(actual, 1.0) / max(estimate, 1.0)


def candidate_ratio(candidates: int, left: int, right: int) -> float:
    """Selectivity of the zone join against the Cartesian product."""
    return candidates / max(1, left * right)


#: Metrics of plan nodes that a measurement adds up, by the name under which it returns them.
_READ = {"shuffleBytesWritten": "shuffle_bytes", "shuffleRecordsWritten": "shuffle_rows", "filesSize": "scan_bytes"}


def _nodes(plan):
    """The nodes of a plan that has run, through adaptive stages; a reused exchange counts where it was made."""
    name = plan.nodeName()
    if name.startswith("AdaptiveSparkPlan"):
        yield from _nodes(plan.executedPlan())
    elif "QueryStage" in name:
        yield from _nodes(plan.plan())
    elif name != "ReusedExchange":
        yield plan
        for k in range(plan.children().size()):
            yield from _nodes(plan.children().apply(k))


def measured(df: DataFrame) -> dict[str, float]:
    """Runs a query and returns rows, seconds, bytes and rows shuffled, bytes and rows scanned, by the metrics of its final plan."""
    began = time.time()
    execution = df._jdf.queryExecution()
    out = {"rows": float(execution.toRdd().count()), "seconds": time.time() - began, "scan_rows": 0.0} | dict.fromkeys(_READ.values(), 0.0)
    for node in _nodes(execution.executedPlan()):
        found = node.metrics()
        for metric, name in _READ.items():
            if found.contains(metric):
                out[name] += float(found.apply(metric).value())
        if node.nodeName().startswith("Scan") and found.contains("numOutputRows"):
            out["scan_rows"] += float(found.apply("numOutputRows").value())
    return out


def staged_bytes(df: DataFrame) -> int:
    """Bytes of the files that a staged or stored table reads."""
    jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
    paths = [jvm.org.apache.hadoop.fs.Path(f) for f in df.inputFiles()]
    return sum(p.getFileSystem(conf).getFileStatus(p).getLen() for p in paths)
