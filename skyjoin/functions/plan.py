"""Plan helpers: columns worked out once, lineage cut in a shared folder, the package on the workers."""

from __future__ import annotations

import io
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark import SparkContext, SparkFiles
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def sealed(df: DataFrame, columns: dict[str, Column]) -> DataFrame:
    """df with these columns (replacing those of the same names), each worked out once a row.

    They come from a generator of one row: the optimizer neither repeats their expressions in what reads them nor pushes a
    filter on them below, where the expressions would be written out again and again. Filters on other columns still go down.
    """
    fresh = F.inline(F.array(F.struct(*[c.alias(n) for n, c in columns.items()])))
    return df.select(*[c for c in df.columns if c not in columns], fresh)


def rounded(column: str, places: int) -> Column:
    """F.round of a column of doubles, to the bit. The decimal arithmetic of F.round, the larger part of a wide match's time, is left to
    values next to a tie and to very large ones: everywhere else the nearest whole number of units, divided once, is the same double.
    """
    c, unit = F.col(column), float(10**places)
    whole = F.floor(c * unit + 0.5)
    plain = (F.abs(c * unit - whole) < 0.499) & whole.between(-(1 << 40), 1 << 40)
    return F.when(plain, whole / F.lit(unit)).otherwise(F.round(c, places))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, spark.checkpoint.dir. Only a local session without it gets one of its own."""
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if folder is None:
        if not context.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir is unset: a folder that all machines share is needed")
        folder = tempfile.mkdtemp(prefix="checkpoint-")
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(folder)
    return folder


def checkpointed(df: DataFrame) -> DataFrame:
    """df written to the shared folder and read back; its lineage ends there."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def importable(spark: SparkSession) -> SparkSession:
    """Sends this package to the Python workers as an archive, once for each context: they need no folder of the driver's."""
    context: SparkContext = spark.sparkContext
    if getattr(context, "_skyjoin_archive", None) is None:
        package = Path(__file__).resolve().parents[1]
        packed = io.BytesIO()
        with zipfile.ZipFile(packed, "w", zipfile.ZIP_DEFLATED) as archive:
            for file in sorted(package.rglob("*.py")):
                archive.write(file, file.relative_to(package.parent).as_posix())
        # Spark's own folder of the driver, from which it serves files to the executors.
        path = Path(SparkFiles.getRootDirectory()) / f"skyjoin-{uuid.uuid4().hex[:8]}.zip"
        path.write_bytes(packed.getvalue())
        context.addPyFile(str(path))
        context._skyjoin_archive = str(path)
    return spark
