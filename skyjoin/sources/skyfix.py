"""Derived sky catalogs: views over the given tables, as DataFrames and as SQL text from the same expressions.

Positions are a function of an object key, noise of a detection key; only integer arithmetic decides, so that two engines
derive the same rows.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.plan import sealed

P = 2147483647
PER_RADIAN = "206264.80624709636e0"


def mix(k: str) -> str:
    return f"(((({k}) % {P}) * 1103515245 + 12345) % {P})"


def uniform(m: str, a: int, b: int, c: int) -> str:
    return f"((CAST((((({m}) * ({m})) % {P}) * {a} + ({m}) * {b} + {c}) % {P} AS DOUBLE) + 5e-1) / 2147483647e0)"


@dataclass(frozen=True)
class Source:
    table: str
    key: str
    obj: str
    sigma: str
    salt: int
    payload: dict[str, str] = field(default_factory=dict)
    where: str = ""


@dataclass(frozen=True)
class Field:
    """Side of the field in degrees (0: the whole sky) and a factor on all errors."""

    side: float = 4.0
    factor: float = 1.0


FINE, CROWD60, CROWD100, CROWD300, FULL = Field(), Field(factor=60.0), Field(factor=100.0), Field(factor=300.0), Field(side=0.0)
SOURCES = {
    "optical": Source("customer", "c_custkey", "c_custkey", "1e-1", 1, {"mag": "20 - c_acctbal / 2000", "is_target": "CASE WHEN c_mktsegment = 'BUILDING' THEN 1 ELSE 0 END", "c_nationkey": "c_nationkey"}),
    "uv": Source("orders", "o_orderkey", "o_custkey", "2e-1", 2, {"mag": "25 - ln(o_totalprice)", "o_orderstatus": "o_orderstatus", "epoch": "o_orderdate"}, "o_orderpriority = '1-URGENT'"),
    "nir": Source("orders", "o_orderkey", "o_custkey", "5e-1", 3, {"mag": "25 - ln(o_totalprice)", "o_orderstatus": "o_orderstatus", "epoch": "o_orderdate"}, "o_orderpriority = '5-LOW'"),
    "transient": Source("events", "event_id", "user_id", "1e-1 + value / 20", 4, {"epoch": "ts", "event_type": "event_type"}),
    "bright_star": Source("supplier", "s_suppkey", "s_suppkey", "1e-3", 6, {"mask_deg": "5e-2"}),
    "survey_caps": Source("nation", "n_nationkey", "n_nationkey", "1e-3", 7, {"region": "n_regionkey", "cap_deg": "6e-1"}),
    "upload": Source("part", "p_partkey", "p_partkey", "3e-1", 8, {"p_retailprice": "p_retailprice"}, "p_retailprice >= 990"),
}


def _stages(s: Source, f: Field) -> list[list[str]]:
    sigma = f"CAST(({s.sigma}) * {f.factor:e} AS DOUBLE)"
    keep = ["key", "obj", "sigma_as", *s.payload]
    if f.side:
        half = f"radians({f.side / 2:e})"
        ra0, dec0 = f"180e0 - {f.side / 2:e} + {f.side:e} * v1", f"degrees(asin(sin({half}) * (2 * v2 - 1)))"
    else:
        ra0, dec0 = "360e0 * v1", "degrees(asin(2 * v2 - 1))"
    return [
        [f"CAST({s.key} AS BIGINT) AS key", f"CAST({s.obj} AS BIGINT) AS obj", f"{sigma} AS sigma_as", *(f"{e} AS {n}" for n, e in s.payload.items()), f"{mix(f'CAST({s.obj} AS BIGINT)')} AS mo", f"{mix(f'CAST({s.key} AS BIGINT)')} AS mk"],
        [*keep, f"{uniform('mo', 48271, 69621, 12345)} AS v1", f"{uniform('mo', 16807, 630360, 777)} AS v2", f"{uniform('mk', 40014, 40692, 1000 + s.salt)} AS g1", f"{uniform('mk', 39373, 742938, 5000 + s.salt)} AS g2"],
        [*keep, f"{ra0} AS ra0", f"{dec0} AS dec0", "sigma_as / 3600e0 * sqrt(-2 * ln(g1)) AS r", "2 * pi() * g2 AS phi"],
        [*keep, "ra0 + r * cos(phi) / cos(radians(dec0)) AS ra1", "dec0 + r * sin(phi) AS dec"],
        [*keep, "ra1 - 360e0 * floor(ra1 / 360e0) AS ra", "dec"],
        [*keep, "ra", "dec", "cos(radians(dec)) * cos(radians(ra)) AS cx", "cos(radians(dec)) * sin(radians(ra)) AS cy", "sin(radians(dec)) AS cz"],
    ]


def catalog(spark: SparkSession, sf_dir: str, name: str, f: Field = FINE) -> DataFrame:
    s = SOURCES[name]
    out = spark.read.parquet(f"{sf_dir}/{s.table}.parquet")
    if s.where:
        out = out.filter(s.where)
    for k, stage in enumerate(_stages(s, f)):
        if not k:
            out = out.selectExpr(*stage)
        else:
            named = {e.rpartition(" AS ")[2]: F.expr(e.rpartition(" AS ")[0] or e) for e in stage}
            out = sealed(out, {n: e for n, e in named.items() if n not in out.columns}).select(*named)
    return out


def catalog_sql(name: str, f: Field = FINE) -> str:
    """The same catalog as one SELECT for an engine that has the given tables as views; w is added."""
    s = SOURCES[name]
    text = s.table + (f" WHERE {s.where}" if s.where else "")
    for k, stage in enumerate(_stages(s, f)):
        text = f"SELECT {', '.join(stage)} FROM {text}" if not k else f"SELECT {', '.join(stage)} FROM ({text}) AS s{k}"
    return f"SELECT *, ({PER_RADIAN} / sigma_as) * ({PER_RADIAN} / sigma_as) AS w FROM ({text}) AS z"


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Natural vectors as directions: the first three components, normalised; one degree of error."""
    from ..functions.sphere import normalize

    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet").selectExpr("vec_id AS key", "label", *(f"CAST(embedding[{k}] AS DOUBLE) AS c{k}" for k in range(3)))
    x, y, z = normalize("c0", "c1", "c2")
    return e.select("key", "label", x.alias("cx"), y.alias("cy"), z.alias("cz")).selectExpr("*", "3600e0 AS sigma_as")


VECTORS_SQL = f"""SELECT key, label, c0 / n AS cx, c1 / n AS cy, c2 / n AS cz, 3600e0 AS sigma_as, ({PER_RADIAN} / 3600e0) * ({PER_RADIAN} / 3600e0) AS w FROM (
  SELECT *, sqrt(c0 * c0 + c1 * c1 + c2 * c2) AS n FROM (SELECT vec_id AS key, label, CAST(embedding[1] AS DOUBLE) AS c0, CAST(embedding[2] AS DOUBLE) AS c1, CAST(embedding[3] AS DOUBLE) AS c2 FROM embeddings) a) b"""
