"""Registry of data sets, user space, zone cache, column metadata and provenance."""

from __future__ import annotations

import hashlib
import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.zones import Grid, sky_columns, zone_table


@dataclass(frozen=True)
class Meta:
    """Ontology identifier, unit and text of a column."""

    ucd: str = ""
    unit: str = ""
    text: str = ""


def describe(df: DataFrame, columns: dict[str, Meta]) -> DataFrame:
    """df with metadata on columns; it lives in the schema and survives Parquet."""
    return df.select(*[F.col(c).alias(c, metadata={"ucd": m.ucd, "unit": m.unit, "text": m.text}) if (m := columns.get(c)) else F.col(c) for c in df.columns])


def metadata_of(df: DataFrame) -> dict[str, dict[str, str]]:
    return {f.name: dict(f.metadata) for f in df.schema.fields if f.metadata}


def provenance(inputs: list[str], limit: float, modes: dict[str, str], text: str | None = None, grid: Grid | None = None, version: int = 1) -> str:
    """A record of how an output was made, for its table properties."""
    return json.dumps({"inputs": inputs, "limit": limit, "modes": modes, "text": text, "grid": [grid.height, grid.cells] if grid else None, "version": version}, sort_keys=True)


def record_on(spark: SparkSession, table: str, record: str) -> None:
    """Keeps a record of how a table was made in its properties."""
    quoted = record.replace("\\", "\\\\").replace("'", "\\'")
    spark.sql(f"ALTER TABLE {table} SET TBLPROPERTIES ('provenance' = '{quoted}')")


@dataclass
class CatalogRegistry:
    """Federations of data sets: names to paths or tables, with prototype schemas that need no data."""

    spark: SparkSession
    entries: dict[str, tuple[str, str]] = field(default_factory=dict)
    prototypes: dict[str, T.StructType] = field(default_factory=dict)

    def add(self, name: str, location: str, form: str = "parquet", prototype: T.StructType | None = None) -> None:
        self.entries[name] = (form, location)
        if prototype:
            self.prototypes[name] = prototype

    def table(self, name: str) -> DataFrame:
        form, location = self.entries[name]
        if form == "table":
            return self.spark.table(location)
        reader = self.spark.read.format(form)
        if form in ("csv", "json"):
            if name not in self.prototypes:
                raise ValueError(f"{name}: plain files need a prototype schema")
            reader = reader.schema(self.prototypes[name])
        if form == "csv":
            reader = reader.option("header", True)
        return reader.load(location)

    def create_empty(self, name: str, table: str) -> None:
        """A physical table after a prototype."""
        self.spark.createDataFrame([], self.prototypes[name]).write.mode("ignore").saveAsTable(table)

    def remote(self, name: str, form: str, **options: str) -> DataFrame:
        """The hook for remote sources: any data source that the session knows."""
        return self.spark.read.format(form).options(**options).load()


class UserSpace:
    """A user's own schema for results and uploads."""

    def __init__(self, spark: SparkSession, user: str):
        if not user.isidentifier():
            raise ValueError("a user name is an identifier")
        self.spark, self.schema = spark, f"user_{user}"
        spark.sql(f"CREATE DATABASE IF NOT EXISTS {self.schema}")

    def put(self, name: str, df: DataFrame, record: str | None = None) -> DataFrame:
        table = f"{self.schema}.{name}"
        df.write.mode("overwrite").saveAsTable(table)
        if record:
            record_on(self.spark, table, record)
        return self.spark.table(table)

    def get(self, name: str) -> DataFrame:
        return self.spark.table(f"{self.schema}.{name}")

    def record(self, name: str) -> str | None:
        rows = self.spark.sql(f"SHOW TBLPROPERTIES {self.schema}.{name}").filter("key = 'provenance'").collect()
        return rows[0].value if rows else None

    def export(self, name: str, path: str, form: str = "parquet") -> None:
        self.get(name).write.mode("overwrite").format(form).option("header", True).save(path)

    def drop(self, name: str) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.schema}.{name}")


class ZoneCache:
    """Zone tables kept as bucketed, sorted tables, so that later joins on (zone, cell) need no shuffle of this side."""

    def __init__(self, spark: SparkSession, schema: str = "default", buckets: int = 64):
        self.spark, self.schema, self.buckets = spark, schema, buckets

    def name(self, catalog: str, version: str, grid: Grid, where: str | None) -> str:
        mark = hashlib.blake2b(json.dumps([catalog, version, grid.height, grid.cells, where]).encode(), digest_size=8).hexdigest()
        return f"{self.schema}.zones_{mark}"

    def get_or_build(self, catalog: str, version: str, df: DataFrame, position: tuple[str, ...], grid: Grid, where: str | None = None) -> DataFrame:
        table = self.name(catalog, version, grid, where)
        if not self.spark.catalog.tableExists(table):
            rows = zone_table(sky_columns(df.filter(where) if where else df, position), grid)
            rows.write.bucketBy(self.buckets, "zone", "cell").sortBy("zone", "cell").mode("overwrite").saveAsTable(table)
        return self.spark.table(table)
