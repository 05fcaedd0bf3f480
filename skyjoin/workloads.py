"""The experiment workloads on derived catalogs: each a query and, where SQL can say it, brute-force SQL without zones."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.evidence import evidence_class, fisher_ln_pdf, ln_bayes_flat, ln_gaussian_property, weight, with_posterior
from .functions.plan import rounded, sealed
from .functions.sphere import chord2, chord_of, separation_as
from .operators import baselines, metrics, relational
from .operators.match import ALLOW, FORBID, REQUIRE, Participant, Trace, classify_dropouts, match_all, objects_of, order_participants, resolve, self_match
from .operators.regions import Cap, Convex, Region, parse_region, pixel_of, pixels, region_join
from .operators.sampling import Link, chosen, mini
from .operators.zones import Grid, pair_table, reached, sky_columns, zone_table
from .plans import planner
from .plans.stats import histogram, wedge_of, wedges
from .sources.skyfix import CROWD60, FINE, FULL, VECTORS_SQL, Field, catalog, catalog_sql, vectors

ERRORS = {"optical": 0.1, "uv": 0.2, "nir": 0.5, "upload": 0.3}
LIMIT = 1e6
CIRCLE = "circle J2000 180 0 60"
#: Loose cuts of the brute-force SQL, arc seconds, by error factor; far wider than any search radius.
CUT = {1.0: 20.0, 60.0: 300.0, 100.0: 500.0, 300.0: 1500.0}


# Queries ---------------------------------------------------------------------------------------------------------------


def part(spark: SparkSession, d: str, name: str, mode: str = REQUIRE, f: Field = FINE, **how) -> Participant:
    error = ERRORS[name] * f.factor if name in ERRORS else "sigma_as"
    return Participant(name, catalog(spark, d, name, f), mode, error=error, **how)


def _fields(names: list[str]) -> list[Column]:
    keys = [F.col(n)["key"].alias(f"{n}_key") for n in names]
    return [*keys, rounded("x.ra", 6).alias("ra"), rounded("x.dec", 6).alias("dec"), rounded("x.ln_bf", 3).alias("ln_bf")]


def flat(df: DataFrame, *names: str) -> DataFrame:
    return df.select(*_fields(list(names)))


def two(spark, d, f=FINE, limit=LIMIT, **how):
    return match_all([part(spark, d, "optical", f=f), part(spark, d, "uv", f=f)], limit, **how)


def three(spark, d, mode=REQUIRE, f=FINE, limit=LIMIT, **how):
    return match_all([part(spark, d, "optical", f=f), part(spark, d, "uv", f=f), part(spark, d, "nir", mode, f)], limit, **how)


def sample_crossmatch(spark: SparkSession, d: str) -> DataFrame:
    """Two required catalogs and an optional one, a class filter, a circle around the first catalog's positions."""
    parts = [part(spark, d, "optical", where="is_target = 1", columns=("mag", "ra", "dec")), part(spark, d, "uv", columns=("mag",)), part(spark, d, "nir", ALLOW, columns=("mag",))]
    m = match_all(parts, LIMIT, region=parse_region(CIRCLE))
    return m.select(*_fields(["optical", "uv", "nir"]), F.round("optical.mag", 6).alias("optical_mag"), F.round("uv.mag", 6).alias("uv_mag"), F.round("nir.mag", 6).alias("nir_mag"))


def region_late(spark, d):
    parts = [part(spark, d, "optical", where="is_target = 1", columns=("mag", "ra", "dec")), part(spark, d, "uv", columns=("mag",)), part(spark, d, "nir", ALLOW, columns=("mag",))]
    m = match_all(parts, LIMIT, region=parse_region(CIRCLE), region_on="post")
    return m.select(*_fields(["optical", "uv", "nir"]), F.round("optical.mag", 6).alias("optical_mag"), F.round("uv.mag", 6).alias("uv_mag"), F.round("nir.mag", 6).alias("nir_mag"))


def match_rejoin_payload(spark, d):
    parts = [part(spark, d, "optical", columns=("mag",)), part(spark, d, "uv", columns=("mag", "o_orderstatus"))]
    m = match_all(parts, LIMIT, payload="rejoin")
    return m.select(*_fields(["optical", "uv"]), F.round("optical.mag", 6).alias("optical_mag"), F.col("uv.o_orderstatus").alias("status"))


def match_three_colocated(spark, d):
    parts = [part(spark, d, "optical", site="a"), part(spark, d, "uv", site="b"), part(spark, d, "nir", site="b")]
    return flat(match_all(parts, LIMIT, plan="colocated"), "optical", "uv", "nir")


def match_three_wedges(spark, d, n: int = 4):
    """The same match in wedges of the anchor's right ascension: disjoint by the anchor, partners with the margin that the limit asks for."""
    parts = [part(spark, d, c) for c in ("optical", "uv", "nir")]
    return flat(planner.execute(parts, LIMIT, "wedges", rate=1.0, n=n), "optical", "uv", "nir")


def match_one_wedge(spark, d):
    """The baseline of one partition."""
    return match_three_wedges(spark, d, 1)


def match_order_estimated(spark, d):
    """Order and cells from samples of the catalogs."""
    return flat(three(spark, d, order="estimated", rate=0.1), "optical", "uv", "nir")


def match_order_static(spark, d):
    """The baseline of whole tables' counts."""
    parts = [part(spark, d, c) for c in ("optical", "uv", "nir")]
    return flat(match_all(parts, LIMIT, order="estimated", rows=planner.static_rows(parts)), "optical", "uv", "nir")


FILTERS = {"optical": "is_target = 1", "uv": "mag < 14", "nir": None}


def _filtered(spark, d):
    return [part(spark, d, c, where=w) for c, w in FILTERS.items()]


def match_filtered_order(spark, d):
    """Selective filters that change the order."""
    return flat(match_all(_filtered(spark, d), LIMIT, order="estimated", rate=1.0), "optical", "uv", "nir")


def filtered_orders(spark, d):
    """The place of each catalog in the order by static counts, and by counts with the query's own filters."""
    parts = _filtered(spark, d)
    found = {a: f.rows for a, f in planner.profiles(parts, 1.0).items()}
    rows = []
    for how, counts in (("static", planner.static_rows(parts)), ("estimated", found)):
        rows += [(how, k, p.alias, counts[p.alias]) for k, p in enumerate(order_participants(parts, counts))]
    return spark.createDataFrame(rows, "how string, place int, catalog string, rows double")


def _four(spark, d, plan):
    parts = [part(spark, d, c, site=s) for c, s in (("optical", "a"), ("uv", "b"), ("nir", "b"), ("transient", "a"))]
    return flat(match_all(parts, LIMIT, plan=plan), "optical", "uv", "nir", "transient")


def match_round_counts(spark, d):
    """Tuples kept after each round, in two orders of the catalogs: what the order costs, counted while the match runs."""
    rows = []
    for order in ("listed", "reversed"):
        trace = Trace(("kept",))
        three(spark, d, f=CROWD60, limit=1e3, order=order, trace=trace).select("optical.key").write.format("noop").mode("overwrite").save()
        rows += [(order, k, n) for k, n in enumerate(n for _, n in trace.counts())]
    return spark.createDataFrame(rows, "plan_order string, round int, kept long")


def candidate_ratio(spark, d):
    """Pairs that the zone join looks at against the Cartesian product, as errors grow: kept pairs, and whether fewer than a part are looked at."""
    sizes, rows = [catalog(spark, d, n).count() for n in ("optical", "uv")], []
    for k in (1.0, 10.0, 60.0):
        trace = Trace()
        two(spark, d, f=Field(factor=k), limit=1e3, trace=trace).select("optical.key").write.format("noop").mode("overwrite").save()
        counts = dict(trace.counts())
        rows.append((k, sizes[0] * sizes[1], counts["kept"], metrics.candidate_ratio(counts["candidates"], *sizes) < 0.05))
    return spark.createDataFrame(rows, "factor double, product long, kept long, selective boolean")


def region_rounds(spark, d):
    """Pairs kept with the region early and late: what the early filter saves."""
    rows = []
    for when in ("owner", "post"):
        parts = [part(spark, d, "optical", columns=("ra", "dec")), part(spark, d, "uv")]
        m = match_all(parts, LIMIT, region=parse_region(CIRCLE), region_on=when, trace=(trace := Trace()))
        n = m.select("optical.key").count()
        rows.append((when, dict(trace.counts())["kept"], n))
    return spark.createDataFrame(rows, "region_on string, kept long, rows long")


def estimate_q_error(spark, d):
    """The factor between estimated and actual rows."""
    e = cardinality_estimates(spark, d)
    high, low = F.greatest("estimate", F.lit(1.0), F.col("actual").cast("double")), F.least(F.greatest("estimate", F.lit(1.0)), F.greatest(F.col("actual").cast("double"), F.lit(1.0)))
    return e.select("name", F.round(high / low, 6).alias("q_error"))


def dropout_report(spark, d):
    """Required pairs by verdict."""
    return dropout_explained(spark, d).groupBy("verdict").agg(F.count("*").alias("n"))


COLOUR = 5.0


def colour_classes(spark, d):
    """Classes by a colour cut after the match, and how many of each the evidence of magnitudes would keep."""
    extra = ln_gaussian_property(F.col("optical.mag"), 1.0, F.col("uv.mag"), 1.0, 3.0)
    m = match_all([part(spark, d, n, f=CROWD60, columns=("mag",)) for n in ("optical", "uv")], 1e3)
    kind = F.when(F.col("optical.mag") - F.col("uv.mag") > COLOUR, "star").otherwise("quasar")
    return m.groupBy(kind.alias("class")).agg(F.count("*").alias("n"), F.sum((F.col("x.ln_bf") + extra >= math.log(1e3)).cast("long")).alias("kept"))


def match_epochs(spark, d):
    """Detections of each object by year, after the match."""
    m = match_all([part(spark, d, "optical"), part(spark, d, "uv", columns=("epoch",))], LIMIT)
    return m.groupBy(F.col("optical.key").alias("optical_key"), F.year("uv.epoch").alias("year")).agg(F.count("*").alias("n"), F.min("uv.key").alias("first_key"))


def match_cached_zones(spark, d):
    """A match against a zone table that is kept bucketed: that side isn't shuffled again."""
    from .sources.catalogs import ZoneCache

    grid = Grid(30.0 / 3600)
    uv = catalog(spark, d, "uv")
    version = uv.agg(F.count("*"), F.expr("bit_xor(xxhash64(key, ra, dec))")).first()
    kept = ZoneCache(spark, buckets=8).get_or_build("uv", str(tuple(version)), uv.select("key", "ra", "dec"), ("ra", "dec"), grid)
    return flat(match_all([part(spark, d, "optical"), Participant("uv", kept, error=0.2, grid=grid)], LIMIT), "optical", "uv")


def region_complement(spark, d):
    """Detections by membership in a circle, in its complement, and in the complement of a union (De Morgan)."""
    a, b = parse_region(CIRCLE), parse_region("circle J2000 181 0.5 45")
    c = catalog(spark, d, "optical")
    inside = {n: r.contains("cx", "cy", "cz") for n, r in (("a", a), ("not_a", ~a), ("none", ~(a | b)), ("both_out", ~a & ~b))}
    return c.groupBy(*[v.alias(n) for n, v in inside.items()]).agg(F.count("*").alias("n"))


def region_areas(spark, d):
    """Areas in square degrees: a circle, its complement, and the caps of the nations added up."""
    square = (180 / math.pi) ** 2
    a = parse_region(CIRCLE)
    caps = [Cap.circle(r.ra, r.dec, r.cap_deg) for r in catalog(spark, d, "survey_caps").select("ra", "dec", "cap_deg").collect()]
    rows = [("circle", a.area()), ("rest", (~a).area()), ("caps", sum(Region((Convex((c,)),)).area() for c in caps))]
    return spark.createDataFrame([(n, round(v * square, 6)) for n, v in rows], "name string, square_deg double")


def mini_documents(spark, d, rate: float = 0.2):
    """A sample of documents with their labels: no orphans."""
    tables = {t: spark.read.parquet(f"{d}/{t}.parquet") for t in ("documents", "labels")}
    kept = mini(tables, "documents", "doc_id", [Link("labels", "doc_id", "documents", "doc_id")], rate)
    rows = [df.agg(F.lit(n).alias("name"), F.count("*").alias("n")) for n, df in kept.items()]
    return rows[0].unionByName(rows[1])


def experiment_costs(spark, d):
    """Costs by the metrics of the final plans: payload carried or fetched later, region early or late, zone cache or none, wedges."""
    from .experiments import costs

    return spark.createDataFrame(costs(spark, d), "experiment string, variant string, rows double, seconds double, shuffle_bytes double, shuffle_rows double, scan_bytes double, scan_rows double")


def pairwise_pruning_lost(spark, d):
    """Triples that a limit on every pair would lose."""
    return flat(three(spark, d, f=CROWD60, limit=1e3, prune="lost"), "optical", "uv", "nir").select("optical_key", "uv_key", "nir_key")


def _self(spark, d):
    return self_match(Participant("uv", catalog(spark, d, "uv"), error=0.2, columns=("obj",)), LIMIT)


def self_match_pairs(spark, d):
    return _self(spark, d).select(F.col("a.key").alias("a_key"), F.col("b.key").alias("b_key"), F.round("x.ln_bf", 3).alias("ln_bf"))


def self_match_groups(spark, d):
    pairs = _self(spark, d).select(F.col("a.key").alias("a"), F.col("b.key").alias("b"))
    return objects_of(pairs, catalog(spark, d, "uv").select("key"))


def match_row_errors(spark, d):
    return flat(match_all([part(spark, d, "optical"), part(spark, d, "transient")], LIMIT), "optical", "transient")


def match_error_classes(spark, d):
    """The same, with the uncertain catalog split by error so that sharp rows keep a small radius."""
    from .operators.zones import by_error

    out = None
    for df, _ in by_error(catalog(spark, d, "transient"), "sigma_as", 3):
        m = flat(match_all([part(spark, d, "optical"), Participant("transient", df, error="sigma_as")], LIMIT), "optical", "transient")
        out = m if out is None else out.unionByName(m)
    return out


def match_cartesian(spark, d):
    m = self_match(Participant("v", vectors(spark, d), position=("cx", "cy", "cz"), error=3600.0, columns=("label",)), 10.0)
    return m.select(F.col("a.key").alias("a_key"), F.col("b.key").alias("b_key"), F.round("x.ln_bf", 3).alias("ln_bf"), (F.col("a.label") == F.col("b.label")).alias("same_label"))


def match_fk_side_tables(spark, d):
    """Ordinary joins beside the match: nation and region of the first member, line items of the second."""
    m = match_all([part(spark, d, "optical", columns=("c_nationkey",)), part(spark, d, "uv")], LIMIT)
    n, r = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("nation", "region"))
    lines = spark.read.parquet(f"{d}/lineitem.parquet").groupBy("l_orderkey").agg(F.count("*").alias("n_lines"), F.round(F.sum("l_quantity"), 2).alias("quantity"))
    m = m.select(F.col("optical.key").alias("optical_key"), F.col("uv.key").alias("uv_key"), F.col("optical.c_nationkey").alias("n_nationkey"))
    m = m.join(F.broadcast(n), "n_nationkey").join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return m.join(lines, F.col("uv_key") == F.col("l_orderkey")).select("optical_key", "uv_key", "n_name", "r_name", "n_lines", "quantity")


def match_upload_list(spark, d):
    """A small uploaded list against a catalog: every match is a chance one here."""
    f = CROWD60
    return flat(match_all([part(spark, d, "upload", f=f), part(spark, d, "optical", f=f)], 10.0), "upload", "optical")


def match_aggregates_cube(spark, d):
    m = match_all([part(spark, d, "optical", columns=("c_nationkey", "is_target")), part(spark, d, "uv")], LIMIT)
    m = m.select(F.col("optical.c_nationkey").alias("nation"), F.col("optical.is_target").alias("target"), F.col("x.ln_bf").alias("b"))
    return m.cube("nation", "target").agg(F.count("*").alias("n"), F.round(F.avg("b"), 3).alias("avg_ln_bf"), F.grouping_id().cast("int").alias("level"))


def within_radius(spark, d):
    out = baselines.match_within(catalog(spark, d, "optical").select("key", "ra", "dec"), catalog(spark, d, "uv").select("key", "ra", "dec"), 1.0)
    return out.select("a_key", "b_key", F.round("sep_as", 3).alias("sep_as"))


def nearest(spark, d):
    out = baselines.nearest_match(catalog(spark, d, "uv").select("key", "ra", "dec"), catalog(spark, d, "optical").select("key", "ra", "dec"), 30.0)
    return out.select("a_key", "b_key", F.round("sep_as", 3).alias("sep_as"))


def brute_force(spark, d):
    c = [catalog(spark, d, n).select("key", "ra", "dec", "sigma_as") for n in ("optical", "uv")]
    return baselines.brute_pairs(c[0], c[1], LIMIT).select("a_key", "b_key", F.round("ln_bf", 3).alias("ln_bf"))


def zones_without_cells(spark, d):
    return flat(two(spark, d, grid=Grid(60 / 3600, cells=False)), "optical", "uv")


def _resolved(policy):
    def run(spark, d):
        m = two(spark, d, f=CROWD60, limit=1e3)
        return flat(resolve(m, policy, [F.col("optical.key")], [F.col("uv.key")], F.round("x.ln_bf", 6)), "optical", "uv")

    return run


GRID = Grid(0.05)


def zone_table_rows(spark, d):
    z = zone_table(sky_columns(catalog(spark, d, "optical", FULL).select("key", "ra", "dec"), ("ra", "dec")), GRID)
    return z.select("key", "zone", "cell")


def pair_table_rows(spark, d):
    a, b = (sky_columns(catalog(spark, d, n).select(F.col("key").alias(f"{n}_key"), "ra", "dec"), ("ra", "dec")).drop("ra", "dec") for n in ("optical", "uv"))
    out = sealed(pair_table(a, b, chord_of(5 / 3600), GRID), {"sep_as": separation_as("__c2")})
    return out.select("optical_key", "uv_key", F.round("sep_as", 3).alias("sep_as"))


def match_table_rows(spark, d):
    """Combined position, its error and the evidence of each pair."""
    m = two(spark, d)
    return m.select(F.col("optical.key").alias("optical_key"), F.col("uv.key").alias("uv_key"), F.round("x.cx", 6).alias("cx"), F.round("x.cy", 6).alias("cy"), F.round("x.cz", 6).alias("cz"), F.round("x.sigma_as", 5).alias("sigma_as"), F.round("x.ln_bf", 3).alias("ln_bf"))


def _near(spark, d):
    """Pairs within 3 arc seconds with both weights and the squared chord."""
    a, b = (sky_columns(catalog(spark, d, n).select(F.col("key").alias(f"{n}_key"), "ra", "dec", F.col("sigma_as").alias(f"{n}_s")), ("ra", "dec")).drop("ra", "dec") for n in ("optical", "uv"))
    return sealed(pair_table(a, b, chord_of(3 / 3600)), {"w1": weight("optical_s"), "w2": weight("uv_s")})


def ln_bayes_values(spark, d):
    m = two(spark, d, limit=1e-3)
    return m.select(F.col("optical.key").alias("optical_key"), F.col("uv.key").alias("uv_key"), F.round("x.ln_bf", 3).alias("ln_bf"))


def ln_bayes_flat_values(spark, d):
    return _near(spark, d).select("optical_key", "uv_key", F.round(ln_bayes_flat("__c2", "w1", "w2"), 3).alias("ln_bf"))


def fisher_density(spark, d):
    p = _near(spark, d)
    return p.select("optical_key", "uv_key", F.round(fisher_ln_pdf("w2", "__c2"), 2).alias("ln_pdf"))


def evidence_classes(spark, d):
    p = sealed(_near(spark, d), {"b": ln_bayes_flat("__c2", "w1", "w2")})
    return p.groupBy(evidence_class("b").alias("class")).agg(F.count("*").alias("n"))


def _posterior(spark, d, f=CROWD60, limit=1e1):
    m = match_all([part(spark, d, "optical", f=f, columns=("obj",)), part(spark, d, "uv", f=f, columns=("obj",))], limit)
    m = m.select(F.col("optical.key").alias("optical_key"), F.col("uv.key").alias("uv_key"), F.col("x.ln_bf").alias("ln_bf"), (F.col("optical.obj") == F.col("uv.obj")).alias("true"))
    counts = [float(catalog(spark, d, n, f).count()) for n in ("optical", "uv")]
    return with_posterior(m, "ln_bf", counts, 16.0 / (360 * 360 / math.pi), rounds=2)


def posterior_probability(spark, d):
    return _posterior(spark, d).select("optical_key", "uv_key", F.round("posterior", 5).alias("posterior"))


def posterior_calibration(spark, d):
    out = metrics.calibration(_posterior(spark, d), "posterior", F.col("true"))
    return out.select("bin", "n", F.round("mean_posterior", 4).alias("mean_posterior"), F.round("true_share", 6).alias("true_share"))


def combined_position(spark, d):
    m = three(spark, d)
    return m.select(F.col("optical.key").alias("optical_key"), F.col("uv.key").alias("uv_key"), F.col("nir.key").alias("nir_key"), F.round("x.ra", 6).alias("ra"), F.round("x.dec", 6).alias("dec"), F.round("x.sigma_as", 5).alias("sigma_as"))


def footprint(spark, d) -> Region:
    """The union of the circles of two regions' nations: a few rows of a fixed table."""
    rows = catalog(spark, d, "survey_caps").filter("region < 2").select("cx", "cy", "cz", "cap_deg").collect()
    return Region(tuple(Convex((Cap(r.cx, r.cy, r.cz, math.cos(math.radians(r.cap_deg))),)) for r in rows))


def masks(spark, d) -> DataFrame:
    return sky_columns(catalog(spark, d, "bright_star").select(F.col("key").alias("mask_key"), F.col("mask_deg").alias("cap_deg"), "ra", "dec"), ("ra", "dec")).drop("ra", "dec")


def dropout_explained(spark, d):
    """Every required pair with its verdict: blocked by a detection, outside the footprint, masked, or a true drop-out."""
    m = classify_dropouts(three(spark, d, FORBID, dropouts=True), "x", footprint(spark, d), None, 24.0)
    m = m.select(F.col("optical.key").alias("optical_key"), F.col("uv.key").alias("uv_key"), F.col("x.cx").alias("cx"), F.col("x.cy").alias("cy"), F.col("x.cz").alias("cz"), "verdict", "upper_limit")
    points = sky_columns(m.select("optical_key", "uv_key", "cx", "cy", "cz"), ("cx", "cy", "cz")).drop("cx", "cy", "cz")
    hidden = region_join(points, masks(spark, d), 0.05).select("optical_key", "uv_key").distinct().withColumn("hidden", F.lit(True))
    m = m.join(hidden, ["optical_key", "uv_key"], "left")
    masked = (F.col("verdict") == "true_dropout") & F.coalesce("hidden", F.lit(False))
    return m.select("optical_key", "uv_key", F.when(masked, "masked").otherwise(F.col("verdict")).alias("verdict"), F.when(~masked, F.col("upper_limit")).alias("upper_limit"))


def dropout_footprint(spark, d):
    return dropout_explained(spark, d).filter("verdict = 'true_dropout'").select("optical_key", "uv_key")


def _inside(text):
    def run(spark, d):
        r = parse_region(text)
        df = r.bounds().filter(catalog(spark, d, "optical"), "ra", "dec")
        return df.filter(r.contains("cx", "cy", "cz")).select("key")

    return run


UNION = "union(circle 180 0 60, circle 181 0.5 45)"
DIFFERENCE = "intersect(circle 180 0 60, not(circle 180.5 0 30))"


def region_join_rows(spark, d):
    points = sky_columns(catalog(spark, d, "optical").select("key", "ra", "dec"), ("ra", "dec")).drop("ra", "dec")
    return region_join(points, masks(spark, d), 0.05).select("key", "mask_key")


def pixel_region_error(spark, d, level: int = 10):
    """Members of a circle by its bitmap against the exact region."""
    r = parse_region(CIRCLE)
    bits = pixels(r, level, spark).withColumn("in_bitmap", F.lit(True))
    df = catalog(spark, d, "optical")
    band, sector = pixel_of("cx", "cy", "cz", level)
    df = sealed(df, {"band": band, "sector": sector, "exact": r.contains("cx", "cy", "cz")})
    # The bitmap of a bounded level is small; the planner broadcasts it if so.
    out = df.join(bits, ["band", "sector"], "left").withColumn("in_bitmap", F.coalesce("in_bitmap", F.lit(False)))
    return out.groupBy("exact", "in_bitmap").agg(F.count("*").alias("n"))


LINKS = [Link("orders", "o_custkey", "customer", "c_custkey"), Link("lineitem", "l_orderkey", "orders", "o_orderkey")]


def mini_catalogs(spark, d, rate: float = 0.05):
    tables = {t: spark.read.parquet(f"{d}/{t}.parquet") for t in ("customer", "orders", "lineitem")}
    out = None
    for name, df in mini(tables, "customer", "c_custkey", LINKS, rate).items():
        row = df.agg(F.lit(name).alias("name"), F.count("*").alias("n"))
        out = row if out is None else out.unionByName(row)
    return out


def ra_histogram(spark, d):
    return histogram(catalog(spark, d, "optical", FULL), 36)


def wedge_bounds(spark, d, n: int = 8):
    bounds = wedges(catalog(spark, d, "optical", FULL), n)
    return spark.createDataFrame([(k, float(b)) for k, b in enumerate(bounds)], "k int, ra double").select("k", F.round("ra", 6).alias("ra"))


def wedge_balance(spark, d, n: int = 8):
    c = catalog(spark, d, "optical", FULL)
    bounds = wedges(c, n)
    out = metrics.balance(c.withColumn("wedge", wedge_of(F.col("ra"), bounds)), "wedge")
    return out.select("parts", F.round("mean", 3).alias("mean"), (F.col("max_over_mean") < 1.2).alias("balanced"))


def wedge_balance_width(spark, d, n: int = 8):
    c = catalog(spark, d, "optical")
    bounds = wedges(c, n, "width")
    return c.withColumn("wedge", wedge_of(F.col("ra"), bounds)).groupBy("wedge").agg(F.count("*").alias("n"))


def cardinality_estimates(spark, d, rate: float = 0.1):
    """Filtered sizes from a mini copy against the full count."""
    out = None
    for name, where in (("optical", "is_target = 1"), ("uv", "mag < 15"), ("nir", "mag < 15")):
        c = catalog(spark, d, name)
        row = c.filter(where).agg(F.lit(name).alias("name"), F.count("*").alias("actual"), F.round(F.coalesce(F.sum(chosen(F.col("obj"), rate).cast("double")), F.lit(0.0)) / rate, 3).alias("estimate"))
        out = row if out is None else out.unionByName(row)
    return out


def _labelled(spark, d, f=CROWD60, limit=1e1, **how):
    m = match_all([part(spark, d, "optical", f=f, columns=("obj",)), part(spark, d, "uv", f=f, columns=("obj",))], limit, **how)
    return m.select(F.col("x.ln_bf").alias("ln_bf"), (F.col("optical.obj") == F.col("uv.obj")).alias("true"))


def accuracy_report(spark, d):
    n = catalog(spark, d, "uv").count()
    out = metrics.accuracy(_labelled(spark, d, limit=1e3), F.col("true"), n)
    return out.select("found", "correct", *[F.round(c, 6).alias(c) for c in ("completeness", "purity", "f1")])


LIMITS = [1e1, 1e2, 1e3, 1e4, 1e5, 1e6]


def roc_by_limit(spark, d):
    return metrics.roc(_labelled(spark, d), F.col("ln_bf"), F.col("true"), LIMITS)


def position_rms(spark, d):
    """Root mean square distance from the true position, of the combined and the single positions of true pairs, arc seconds."""
    truth = catalog(spark, d, "optical", replace(FINE, factor=1e-9)).select(F.col("obj").alias("o"), F.col("cx").alias("tx"), F.col("cy").alias("ty"), F.col("cz").alias("tz"))
    m = match_all([part(spark, d, "optical", columns=("obj", "cx", "cy", "cz")), part(spark, d, "uv", columns=("obj", "cx", "cy", "cz"))], LIMIT).filter("optical.obj = uv.obj").withColumn("o", F.col("optical.obj"))
    m = m.join(truth, "o")
    parts = {}
    for name in ("x", "optical", "uv"):
        parts[name] = chord2([F.col(name)[c] for c in ("cx", "cy", "cz")], ("tx", "ty", "tz"))
    m = sealed(m, {f"c_{k}": v for k, v in parts.items()})
    return m.agg(*[F.round(F.sqrt(F.avg(f"c_{k}")) * 206264.80624709636, 4).alias(f"rms_{k}") for k in parts])


def replication_factor(spark, d):
    """Rows that the border copies add, for three cell sizes."""
    c = sky_columns(catalog(spark, d, "optical").select("key", "ra", "dec"), ("ra", "dec"))
    out = None
    for h in (10.0, 30.0, 300.0):
        row = reached(c, Grid(h / 3600), 3 / 3600).agg(F.lit(h).alias("height_as"), F.count("*").alias("copies"))
        out = row if out is None else out.unionByName(row)
    return out


FACTORS = (10.0, 30.0, 60.0, 100.0)


def accuracy_by_crowding(spark, d):
    """Completeness and purity of the pair match as errors grow against the density.

    Rows and density come from one look at the catalogs: errors of arc seconds change neither over a degree, and a look for each
    factor is two more plans for the driver.
    """
    found, out = planner.profiles([part(spark, d, "optical"), part(spark, d, "uv")], 1.0), None
    how = {"rows": {a: f.rows for a, f in found.items()}, "density": max(f.densest for f in found.values()) or None}
    for k in FACTORS:
        row = metrics.accuracy(_labelled(spark, d, Field(factor=k), 1e3, **how), F.col("true"), found["uv"].rows).withColumn("factor", F.lit(k))
        out = row if out is None else out.unionByName(row)
    return out.select("factor", "found", "correct", F.round("completeness", 6).alias("completeness"), F.round("purity", 6).alias("purity"))


def colour_evidence(spark, d):
    """Positions and magnitudes together: evidence of independent properties adds up."""
    extra = ln_gaussian_property(F.col("optical.mag"), 1.0, F.col("uv.mag"), 1.0, 3.0)
    parts = [part(spark, d, n, f=CROWD60, columns=("mag",)) for n in ("optical", "uv")]
    m = match_all(parts, 1e3, extra_evidence=extra)
    return m.select(F.col("optical.key").alias("optical_key"), F.col("uv.key").alias("uv_key"), F.round("x.ln_total", 3).alias("ln_total"))


def cap_prior(spark, d):
    """The prior over the field instead of the whole sphere: the same limit on evidence asks for closer pairs."""
    return flat(two(spark, d, f=CROWD60, limit=10.0, prior_area=16 * (math.pi / 180) ** 2), "optical", "uv")


def bitmap_levels(spark, d):
    """Wrong members of a circle by the resolution of its bitmap."""
    out = None
    for level in (6, 8, 10):
        row = pixel_region_error(spark, d, level).filter("exact <> in_bitmap").agg(F.lit(level).alias("level"), F.coalesce(F.sum("n"), F.lit(0)).alias("wrong"))
        out = row if out is None else out.unionByName(row)
    return out


# Brute-force SQL -------------------------------------------------------------------------------------------------------


def ctes(*names: str, f: Field = FINE) -> str:
    return ", ".join(f"{n} AS ({catalog_sql(n, f)})" for n in names)


def c2(a: str, b: str) -> str:
    return " + ".join(f"({a}.c{k} - {b}.c{k}) * ({a}.c{k} - {b}.c{k})" for k in "xyz")


def ln_b(*names: str, w: str = "w") -> str:
    total = " + ".join(f"pow({' + '.join(f'{n}.{w} * {n}.c{k}' for n in names)}, 2)" for k in "xyz")
    cross = " + ".join(f"{a}.{w} * {b}.{w} * ({c2(a, b)})" for i, a in enumerate(names) for b in names[:i])
    weights = " + ".join(f"{n}.{w}" for n in names)
    return f"(-({cross}) / ({weights} + sqrt({total})) + {' + '.join(f'ln(2 * {n}.{w})' for n in names)} - ln(2 * sqrt({total})))"


def near(a: str, b: str, ta: str, tb: str, cut: float, columns: str = "", more: str = "") -> str:
    """Key pairs within a cut in arc seconds."""
    chord = chord_of(cut / 3600) ** 2
    return f"SELECT {a}.key AS {a}_key, {b}.key AS {b}_key{columns} FROM {ta} {a} JOIN {tb} {b} ON {b}.dec BETWEEN {a}.dec - {cut / 3600!r} AND {a}.dec + {cut / 3600!r} AND {c2(a, b)} <= {chord!r}{more}"


def place(*names: str) -> str:
    x, y, z = (f"({' + '.join(f'{n}.w * {n}.c{k}' for n in names)})" for k in "xyz")
    ra = f"degrees(atan2({y}, {x}))"
    return f"round({ra} - 360 * floor({ra} / 360), 6) AS ra, round(degrees(atan2({z}, sqrt({x} * {x} + {y} * {y}))), 6) AS dec, round({ln_b(*names)}, 3) AS ln_bf"


def two_sql(f=FINE, limit=LIMIT, a="optical", b="uv", extra="", where=""):
    return f"WITH {ctes(a, b, f=f)}, p AS ({near('a', 'b', a, b, CUT[f.factor])}) SELECT a.key AS {a}_key, b.key AS {b}_key, {place('a', 'b')}{extra} FROM p JOIN {a} a ON a.key = p.a_key JOIN {b} b ON b.key = p.b_key WHERE {ln_b('a', 'b')} >= ln({limit!r}){where}"


def _triples(f, limit):
    cut = CUT[f.factor]
    return f"""{ctes('optical', 'uv', 'nir', f=f)},
ab AS ({near('a', 'b', 'optical', 'uv', cut)}), ac AS ({near('a', 'c', 'optical', 'nir', cut)}),
full3 AS (SELECT a.key AS optical_key, b.key AS uv_key, c.key AS nir_key, {place('a', 'b', 'c')}, {ln_b('a', 'b', 'c')} AS b3
  FROM ab JOIN ac USING (a_key) JOIN optical a ON a.key = a_key JOIN uv b ON b.key = b_key JOIN nir c ON c.key = c_key WHERE {ln_b('a', 'b', 'c')} >= ln({limit!r})),
pairs AS (SELECT a.key AS optical_key, b.key AS uv_key, {place('a', 'b')} FROM ab JOIN optical a ON a.key = a_key JOIN uv b ON b.key = b_key WHERE {ln_b('a', 'b')} >= ln({limit!r})),
alone AS (SELECT * FROM pairs p WHERE NOT EXISTS (SELECT 1 FROM full3 t WHERE t.optical_key = p.optical_key AND t.uv_key = p.uv_key))"""


def three_sql(kind, f=FINE, limit=LIMIT):
    body = {
        "require": "SELECT optical_key, uv_key, nir_key, ra, dec, ln_bf FROM full3",
        "allow": "SELECT optical_key, uv_key, nir_key, ra, dec, ln_bf FROM full3 UNION ALL SELECT optical_key, uv_key, NULL, ra, dec, ln_bf FROM alone",
        "forbid": "SELECT optical_key, uv_key, ra, dec, ln_bf FROM alone",
    }[kind]
    return f"WITH {_triples(f, limit)} {body}"


def sample_sql() -> str:
    v = (-1.0, 0.0, 0.0)
    inside = f"o.cx * {v[0]!r} >= {math.cos(math.radians(1.0))!r}"
    return f"""WITH {_triples(FINE, LIMIT)}, m AS (SELECT optical_key, uv_key, nir_key, ra, dec, ln_bf FROM full3 UNION ALL SELECT optical_key, uv_key, NULL, ra, dec, ln_bf FROM alone)
SELECT m.*, round(o.mag, 6) AS optical_mag, round(u.mag, 6) AS uv_mag, round(n.mag, 6) AS nir_mag FROM m JOIN optical o ON o.key = m.optical_key JOIN uv u ON u.key = m.uv_key LEFT JOIN nir n ON n.key = m.nir_key WHERE o.is_target = 1 AND {inside}"""


def near_sql(select: str, tail: str = "") -> str:
    return f"WITH {ctes('optical', 'uv')}, p AS ({near('a', 'b', 'optical', 'uv', 3.0)}), q AS (SELECT p.a_key AS optical_key, p.b_key AS uv_key, a.w AS w1, b.w AS w2, {c2('a', 'b')} AS c FROM p JOIN optical a ON a.key = p.a_key JOIN uv b ON b.key = p.b_key), r AS (SELECT *, ln(2) - ln(1 / w1 + 1 / w2) - c / (2 * (1 / w1 + 1 / w2)) AS flat FROM q) SELECT {select} FROM r{tail}"


SELF = f"WITH {ctes('uv')}, p AS ({near('a', 'b', 'uv', 'uv', 20.0, more=' AND a.key < b.key')}), m AS (SELECT a.key AS a_key, b.key AS b_key, round({ln_b('a', 'b')}, 3) AS ln_bf FROM p JOIN uv a ON a.key = p.a_key JOIN uv b ON b.key = p.b_key WHERE {ln_b('a', 'b')} >= ln({LIMIT!r}))"
SELF_GROUPS = SELF.replace("WITH ", "WITH RECURSIVE ", 1) + ", e AS (SELECT a_key AS a, b_key AS b FROM m UNION SELECT b_key, a_key FROM m), r AS (SELECT key AS a, key AS b FROM uv UNION SELECT r.a, e.b FROM r JOIN e ON e.a = r.b) SELECT a AS key, min(b) AS object FROM r GROUP BY a"
VERDICT = f"""WITH {_triples(FINE, LIMIT)}, {ctes('survey_caps', 'bright_star')}, held AS (SELECT p.optical_key, p.uv_key, NOT EXISTS (SELECT 1 FROM alone l WHERE l.optical_key = p.optical_key AND l.uv_key = p.uv_key) AS blocked,
  (a.w * a.cx + b.w * b.cx) AS x, (a.w * a.cy + b.w * b.cy) AS y, (a.w * a.cz + b.w * b.cz) AS z FROM pairs p JOIN optical a ON a.key = p.optical_key JOIN uv b ON b.key = p.uv_key),
u AS (SELECT optical_key, uv_key, blocked, x / sqrt(x * x + y * y + z * z) AS cx, y / sqrt(x * x + y * y + z * z) AS cy, z / sqrt(x * x + y * y + z * z) AS cz FROM held),
v AS (SELECT *, CASE WHEN blocked THEN 'blocked'
  WHEN NOT EXISTS (SELECT 1 FROM survey_caps s WHERE s.region < 2 AND u.cx * s.cx + u.cy * s.cy + u.cz * s.cz >= cos(radians(s.cap_deg))) THEN 'not_observed'
  WHEN EXISTS (SELECT 1 FROM bright_star s WHERE {c2('u', 's')} <= pow(2 * sin(radians(s.mask_deg) / 2), 2)) THEN 'masked' ELSE 'true_dropout' END AS verdict FROM u)
"""


def _circle(ra, dec, deg, a="o"):
    x, y, z = (math.cos(math.radians(dec)) * math.cos(math.radians(ra)), math.cos(math.radians(dec)) * math.sin(math.radians(ra)), math.sin(math.radians(dec)))
    return f"{a}.cx * {x!r} + {a}.cy * {y!r} + {a}.cz * {z!r} >= {math.cos(math.radians(deg))!r}"


def _labelled_sql(limit=1e1, f=CROWD60):
    return f"{ctes('optical', 'uv', f=f)}, p AS ({near('a', 'b', 'optical', 'uv', max(300.0, 5 * f.factor))}), m AS (SELECT a.key AS optical_key, b.key AS uv_key, {ln_b('a', 'b')} AS ln_bf, a.obj = b.obj AS yes FROM p JOIN optical a ON a.key = p.a_key JOIN uv b ON b.key = p.b_key WHERE {ln_b('a', 'b')} >= ln({limit!r}))"


def _posterior_sql(rounds=2):
    s = 16.0 / (360 * 360 / math.pi)
    text = f"{_labelled_sql()}, n0 AS (SELECT (SELECT count(*) FROM optical) / {s!r} AS n1, (SELECT count(*) FROM uv) / {s!r} AS n2), k0 AS (SELECT least(n1, n2) AS n FROM n0)"
    odds = "(ln(n / (n1 * n2)) - ln(1 - n / (n1 * n2)))"
    for k in range(rounds):
        text += f", k{k + 1} AS (SELECT greatest(least((SELECT sum(1 / (1 + exp(-(ln_bf + {odds})))) FROM m, n0, k{k}) / {s!r}, least(n1, n2)), 1e-9) AS n FROM n0)"
    return text + f", post AS (SELECT optical_key, uv_key, yes, 1 / (1 + exp(-(ln_bf + {odds}))) AS posterior FROM m, n0, k{rounds})"


PM = "(((({0}) % 2147483647) * 1103515245 + 12345) % 2147483647)"


def _chosen(k, rate):
    m = PM.format(k)
    return f"(({m} * {m}) % 2147483647) < {int(rate * 2147483647)}"


def _zone(h):
    worst = f"least(90, greatest(abs(zone * {h!r} - 90), abs(zone * {h!r} - 90 + {h!r})))"
    n = f"greatest(1, floor(360 * cos(radians({worst})) / {h!r}))"
    return f"WITH {ctes('optical', f=FULL)}, z AS (SELECT key, ra, CAST(floor((dec + 90) / {h!r}) AS INT) AS zone FROM optical) SELECT key, zone, CAST(least({n} - 1, floor(ra * {n} / 360)) AS BIGINT) AS cell FROM z"


Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {
    "sample_crossmatch": sample_crossmatch,
    "sample_region_late": region_late,
    "match_two_required": lambda s, d: flat(two(s, d), "optical", "uv"),
    "match_three_required": lambda s, d: flat(three(s, d), "optical", "uv", "nir"),
    "match_optional_third": lambda s, d: flat(three(s, d, ALLOW), "optical", "uv", "nir"),
    "match_dropout": lambda s, d: flat(three(s, d, FORBID), "optical", "uv"),
    "match_three_cascading": lambda s, d: flat(three(s, d, plan="cascading"), "optical", "uv", "nir"),
    "match_three_colocated": match_three_colocated,
    "match_three_wedges": match_three_wedges,
    "match_order_reversed": lambda s, d: flat(three(s, d, order="reversed"), "optical", "uv", "nir"),
    "match_one_wedge": match_one_wedge,
    "match_order_estimated": match_order_estimated,
    "match_order_static": match_order_static,
    "match_filtered_order": match_filtered_order,
    "filtered_orders": filtered_orders,
    "match_four_cascading": lambda s, d: _four(s, d, "cascading"),
    "match_four_colocated": lambda s, d: _four(s, d, "colocated"),
    "match_cached_zones": match_cached_zones,
    "match_epochs": match_epochs,
    "match_round_counts": match_round_counts,
    "candidate_ratio": candidate_ratio,
    "region_rounds": region_rounds,
    "region_complement": region_complement,
    "region_areas": region_areas,
    "estimate_q_error": estimate_q_error,
    "dropout_report": dropout_report,
    "colour_classes": colour_classes,
    "mini_documents": mini_documents,
    "experiment_costs": experiment_costs,
    "match_no_pruning": lambda s, d: flat(three(s, d, prune="none"), "optical", "uv", "nir"),
    "match_rejoin_payload": match_rejoin_payload,
    "match_whole_sky": lambda s, d: flat(two(s, d, f=FULL), "optical", "uv"),
    "match_row_errors": match_row_errors,
    "match_error_classes": match_error_classes,
    "match_cartesian": match_cartesian,
    "match_fk_side_tables": match_fk_side_tables,
    "match_upload_list": match_upload_list,
    "match_aggregates_cube": match_aggregates_cube,
    "crowded_pairs": lambda s, d: flat(two(s, d, f=CROWD60, limit=1e3), "optical", "uv"),
    "crowded_triples": lambda s, d: flat(three(s, d, f=CROWD60, limit=1e3), "optical", "uv", "nir"),
    "crowded_optional": lambda s, d: flat(three(s, d, ALLOW, f=CROWD60, limit=1e3), "optical", "uv", "nir"),
    "crowded_dropout": lambda s, d: flat(three(s, d, FORBID, f=CROWD60, limit=1e3), "optical", "uv"),
    "pairwise_pruning_lost": pairwise_pruning_lost,
    "self_match": self_match_pairs,
    "self_match_groups": self_match_groups,
    "within_radius": within_radius,
    "nearest": nearest,
    "brute_force": brute_force,
    "zones_without_cells": zones_without_cells,
    "best_match": _resolved("best"),
    "mutual_best": _resolved("mutual"),
    "zone_table": zone_table_rows,
    "pair_table": pair_table_rows,
    "match_table": match_table_rows,
    "ln_bayes_values": ln_bayes_values,
    "ln_bayes_flat": ln_bayes_flat_values,
    "fisher_density": fisher_density,
    "evidence_class": evidence_classes,
    "posterior_probability": posterior_probability,
    "posterior_calibration": posterior_calibration,
    "combined_position": combined_position,
    "dropout_footprint": dropout_footprint,
    "dropout_explained": dropout_explained,
    "region_filter": _inside(CIRCLE),
    "region_union": _inside(UNION),
    "region_difference": _inside(DIFFERENCE),
    "region_join": region_join_rows,
    "pixel_region_error": pixel_region_error,
    "mini_catalogs": mini_catalogs,
    "ra_histogram": ra_histogram,
    "wedge_bounds": wedge_bounds,
    "wedge_balance": wedge_balance,
    "wedge_balance_width": wedge_balance_width,
    "cardinality_estimates": cardinality_estimates,
    "accuracy_report": accuracy_report,
    "roc_by_limit": roc_by_limit,
    "position_rms": position_rms,
    "replication_factor": replication_factor,
    "accuracy_by_crowding": accuracy_by_crowding,
    "colour_evidence": colour_evidence,
    "cap_prior": cap_prior,
    "bitmap_levels": bitmap_levels,
}

_THREE = three_sql("require")
SQL: dict[str, str] = {
    "sample_crossmatch": sample_sql(),
    "sample_region_late": sample_sql(),
    "match_two_required": two_sql(),
    **dict.fromkeys(("match_three_required", "match_three_cascading", "match_three_colocated", "match_three_wedges", "match_one_wedge", "match_order_reversed", "match_order_estimated", "match_order_static", "match_no_pruning"), _THREE),
    "match_optional_third": three_sql("allow"),
    "match_dropout": three_sql("forbid"),
    "match_rejoin_payload": two_sql(extra=", round(a.mag, 6) AS optical_mag, b.o_orderstatus AS status"),
    "match_whole_sky": two_sql(f=FULL),
    **dict.fromkeys(("match_row_errors", "match_error_classes"), f"WITH {ctes('optical', 'transient')}, p AS ({near('a', 'b', 'optical', 'transient', 300.0)}) SELECT a.key AS optical_key, b.key AS transient_key, {place('a', 'b')} FROM p JOIN optical a ON a.key = p.a_key JOIN transient b ON b.key = p.b_key WHERE {ln_b('a', 'b')} >= ln({LIMIT!r})"),
    "match_cartesian": f"WITH v AS ({VECTORS_SQL}) SELECT a.key AS a_key, b.key AS b_key, round({ln_b('a', 'b')}, 3) AS ln_bf, a.label = b.label AS same_label FROM v a JOIN v b ON a.key < b.key WHERE {ln_b('a', 'b')} >= ln(10.0)",
    "match_fk_side_tables": f"WITH m AS ({two_sql(extra=', a.c_nationkey')}), l AS (SELECT l_orderkey, count(*) AS n_lines, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY 1) SELECT optical_key, uv_key, n_name, r_name, n_lines, quantity FROM m JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey JOIN l ON l_orderkey = uv_key",
    "match_upload_list": two_sql(f=CROWD60, limit=10.0, a="upload", b="optical"),
    "match_aggregates_cube": f"WITH m AS ({two_sql(extra=', a.c_nationkey AS nation, a.is_target AS target, ' + ln_b('a', 'b') + ' AS b')}) SELECT nation, target, count(*) AS n, round(avg(b), 3) AS avg_ln_bf, CAST(grouping(nation, target) AS INT) AS level FROM m GROUP BY CUBE (nation, target)",
    "crowded_pairs": two_sql(f=CROWD60, limit=1e3),
    "crowded_triples": three_sql("require", CROWD60, 1e3),
    "crowded_optional": three_sql("allow", CROWD60, 1e3),
    "crowded_dropout": three_sql("forbid", CROWD60, 1e3),
    "pairwise_pruning_lost": f"WITH {_triples(CROWD60, 1e3)} SELECT optical_key, uv_key, nir_key FROM full3 t WHERE NOT EXISTS (SELECT 1 FROM pairs p WHERE p.optical_key = t.optical_key AND p.uv_key = t.uv_key)",
    "self_match": SELF + " SELECT * FROM m",
    "self_match_groups": SELF_GROUPS,
    "within_radius": f"WITH {ctes('optical', 'uv')}, p AS ({near('a', 'b', 'optical', 'uv', 1.0, columns=', ' + c2('a', 'b') + ' AS c')}) SELECT a_key, b_key, round(2 * asin(sqrt(c) / 2) * 206264.80624709636, 3) AS sep_as FROM p",
    "nearest": f"WITH {ctes('optical', 'uv')}, p AS ({near('a', 'b', 'uv', 'optical', 30.0, columns=', ' + c2('a', 'b') + ' AS c')}) SELECT a_key, b_key, round(2 * asin(sqrt(c) / 2) * 206264.80624709636, 3) AS sep_as FROM p QUALIFY row_number() OVER (PARTITION BY a_key ORDER BY c, b_key) = 1",
    "brute_force": f"SELECT optical_key AS a_key, uv_key AS b_key, ln_bf FROM ({two_sql()}) q",
    "zones_without_cells": two_sql(),
    "best_match": f"SELECT * EXCLUDE (b) FROM ({two_sql(f=CROWD60, limit=1e3, extra=', round(' + ln_b('a', 'b') + ', 6) AS b')}) q QUALIFY row_number() OVER (PARTITION BY optical_key ORDER BY b DESC, uv_key) = 1",
    "mutual_best": f"SELECT * EXCLUDE (b) FROM ({two_sql(f=CROWD60, limit=1e3, extra=', round(' + ln_b('a', 'b') + ', 6) AS b')}) q QUALIFY row_number() OVER (PARTITION BY optical_key ORDER BY b DESC, uv_key) = 1 AND row_number() OVER (PARTITION BY uv_key ORDER BY b DESC, optical_key) = 1",
    "zone_table": _zone(GRID.height),
    "pair_table": f"WITH {ctes('optical', 'uv')}, p AS ({near('a', 'b', 'optical', 'uv', 5.0, columns=', ' + c2('a', 'b') + ' AS c')}) SELECT a_key AS optical_key, b_key AS uv_key, round(2 * asin(sqrt(c) / 2) * 206264.80624709636, 3) AS sep_as FROM p",
    "match_table": f"WITH q AS ({two_sql(extra=', a.w * a.cx + b.w * b.cx AS x, a.w * a.cy + b.w * b.cy AS y, a.w * a.cz + b.w * b.cz AS z')}) SELECT optical_key, uv_key, round(x / sqrt(x * x + y * y + z * z), 6) AS cx, round(y / sqrt(x * x + y * y + z * z), 6) AS cy, round(z / sqrt(x * x + y * y + z * z), 6) AS cz, round(206264.80624709636 / sqrt(sqrt(x * x + y * y + z * z)), 5) AS sigma_as, ln_bf FROM q",
    "ln_bayes_values": f"SELECT optical_key, uv_key, ln_bf FROM ({two_sql(limit=1e-3)}) q",
    "ln_bayes_flat": near_sql("optical_key, uv_key, round(flat, 3) AS ln_bf"),
    "fisher_density": near_sql(f"optical_key, uv_key, round(ln(w2) - {math.log(2 * math.pi)!r} - w2 * (c / 2), 2) AS ln_pdf"),
    "evidence_class": near_sql(f"CASE WHEN flat >= {math.log(100.0)!r} THEN 'match' WHEN flat <= {math.log(0.01)!r} THEN 'separate' ELSE 'undecided' END AS class, count(*) AS n", " GROUP BY 1"),
    "posterior_probability": f"WITH {_posterior_sql()} SELECT optical_key, uv_key, round(posterior, 5) AS posterior FROM post",
    "posterior_calibration": f"WITH {_posterior_sql()} SELECT CAST(least(9, floor(posterior * 10)) AS INT) AS bin, count(*) AS n, round(avg(posterior), 4) AS mean_posterior, round(avg(CASE WHEN yes THEN 1.0 ELSE 0.0 END), 6) AS true_share FROM post GROUP BY 1",
    "combined_position": f"WITH {_triples(FINE, LIMIT)}, s AS (SELECT t.optical_key, t.uv_key, t.nir_key, t.ra, t.dec, " + " + ".join(f"pow(a.w * a.c{k} + b.w * b.c{k} + c.w * c.c{k}, 2)" for k in "xyz") + " AS q FROM full3 t JOIN optical a ON a.key = t.optical_key JOIN uv b ON b.key = t.uv_key JOIN nir c ON c.key = t.nir_key) SELECT optical_key, uv_key, nir_key, ra, dec, round(206264.80624709636 / sqrt(sqrt(q)), 5) AS sigma_as FROM s",
    "dropout_explained": VERDICT + "SELECT optical_key, uv_key, verdict, CASE WHEN verdict = 'true_dropout' THEN CAST(24.0 AS DOUBLE) END AS upper_limit FROM v",
    "dropout_footprint": VERDICT + "SELECT optical_key, uv_key FROM v WHERE verdict = 'true_dropout'",
    "region_filter": f"WITH {ctes('optical')} SELECT key FROM optical o WHERE {_circle(180, 0, 1.0)}",
    "region_union": f"WITH {ctes('optical')} SELECT key FROM optical o WHERE {_circle(180, 0, 1.0)} OR {_circle(181, 0.5, 0.75)}",
    "region_difference": f"WITH {ctes('optical')} SELECT key FROM optical o WHERE {_circle(180, 0, 1.0)} AND NOT ({_circle(180.5, 0, 0.5)})",
    "region_join": f"WITH {ctes('optical', 'bright_star')} SELECT o.key, s.key AS mask_key FROM optical o JOIN bright_star s ON {c2('o', 's')} <= pow(2 * sin(radians(s.mask_deg) / 2), 2)",
    "pixel_region_error": f"""WITH {ctes('optical')}, g AS (SELECT *, least(1023, floor((cz + 1) / 2 * 1024)) AS band, least(2047, floor((degrees(atan2(cy, cx)) - 360 * floor(degrees(atan2(cy, cx)) / 360)) / 360 * 2048)) AS sector FROM optical),
h AS (SELECT {_circle(180, 0, 1.0, 'g')} AS exact, (band + 0.5) / 1024 * 2 - 1 AS z, (sector + 0.5) / 2048 * 2 * pi() AS a FROM g)
SELECT exact, -sqrt(1 - z * z) * cos(a) >= {math.cos(math.radians(1.0))!r} AS in_bitmap, count(*) AS n FROM h GROUP BY 1, 2""",
    "mini_catalogs": f"WITH c AS (SELECT c_custkey FROM customer WHERE {_chosen('c_custkey', 0.05)}), o AS (SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM c)) SELECT 'customer' AS name, (SELECT count(*) FROM c) AS n UNION ALL SELECT 'orders', (SELECT count(*) FROM o) UNION ALL SELECT 'lineitem', (SELECT count(*) FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM o))",
    "ra_histogram": f"WITH {ctes('optical', f=FULL)} SELECT CAST(least(35, floor(ra / 360 * 36)) AS INT) AS bin, count(*) AS n FROM optical GROUP BY 1",
    "wedge_balance": f"WITH {ctes('optical', f=FULL)} SELECT CAST(8 AS BIGINT) AS parts, round(count(*) / 8, 3) AS mean, true AS balanced FROM optical",
    "wedge_balance_width": f"WITH {ctes('optical')} SELECT CAST(least(7, floor(ra / 45)) AS INT) AS wedge, count(*) AS n FROM optical GROUP BY 1",
    "cardinality_estimates": " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS actual, round(count(*) FILTER (WHERE {_chosen('obj', 0.1)}) / CAST(0.1 AS DOUBLE), 3) AS estimate FROM ({catalog_sql(n)}) q WHERE {w}" for n, w in (("optical", "is_target = 1"), ("uv", "mag < 15"), ("nir", "mag < 15"))),
    "accuracy_report": f"WITH {_labelled_sql(1e3)}, t AS (SELECT count(*) AS found, count(*) FILTER (WHERE yes) AS correct, (SELECT count(*) FROM uv) AS total FROM m) SELECT found, correct, round(correct / total, 6) AS completeness, round(correct / found, 6) AS purity, round(2 * correct / (found + total), 6) AS f1 FROM t",
    "roc_by_limit": f"WITH {_labelled_sql()} SELECT CAST(l AS DOUBLE) AS evidence, count(*) FILTER (WHERE ln_bf >= ln(l) AND yes) AS correct, count(*) FILTER (WHERE ln_bf >= ln(l) AND NOT yes) AS false_pairs FROM m, (SELECT unnest([1e1, 1e2, 1e3, 1e4, 1e5, 1e6]) AS l) q GROUP BY l",
}

QUERIES |= relational.QUERIES
SQL |= relational.SQL | {
    "match_text_query": sample_sql(),
    "stream_match": f"SELECT optical_key, transient_key FROM ({SQL['match_row_errors']}) q",
    **dict.fromkeys(("job_retry", "job_resume"), f"SELECT optical_key, uv_key FROM ({two_sql()}) q"),
}
_TOTAL = f"({ln_b('a', 'b')} + 0.5 * ln(20.0 / 2) - pow(a.mag - b.mag, 2) / 2 * (1 / 2.0 - 1 / 20.0))"
_CAP_LIMIT = 10.0 / (4 * math.pi / (16 * (math.pi / 180) ** 2))


def _pixel_sql(level: int) -> str:
    n = 1 << level
    inner = SQL["pixel_region_error"].replace("1023", str(n - 1)).replace("2047", str(2 * n - 1)).replace("2048", str(2 * n)).replace("1024", str(n))
    return f"SELECT {level} AS level, CAST(coalesce(sum(n), 0) AS BIGINT) AS wrong FROM ({inner}) q{level} WHERE exact <> in_bitmap"


SQL |= {
    "accuracy_by_crowding": " UNION ALL ".join(
        f"SELECT CAST({k} AS DOUBLE) AS factor, found, correct, round(correct / total, 6) AS completeness, round(correct / found, 6) AS purity FROM (WITH {_labelled_sql(1e3, Field(factor=k))} SELECT count(*) AS found, count(*) FILTER (WHERE yes) AS correct, (SELECT count(*) FROM uv) AS total FROM m) f{k:.0f}"
        for k in FACTORS
    ),
    "colour_evidence": f"WITH {ctes('optical', 'uv', f=CROWD60)}, p AS ({near('a', 'b', 'optical', 'uv', 300.0)}) SELECT a.key AS optical_key, b.key AS uv_key, round({_TOTAL}, 3) AS ln_total FROM p JOIN optical a ON a.key = p.a_key JOIN uv b ON b.key = p.b_key WHERE {ln_b('a', 'b')} >= ln(1000.0) AND {_TOTAL} >= ln(1000.0)",
    "cap_prior": two_sql(f=CROWD60, limit=_CAP_LIMIT),
    "bitmap_levels": " UNION ALL ".join(_pixel_sql(k) for k in (6, 8, 10)),
}

_TRUE = catalog_sql("optical", replace(FINE, factor=1e-9))
_RMS = ", ".join(f"round(sqrt(avg(pow({x} - t.cx, 2) + pow({y} - t.cy, 2) + pow({z} - t.cz, 2))) * 206264.80624709636, 4) AS rms_{n}" for n, x, y, z in (("x", "m.x / m.n", "m.y / m.n", "m.z / m.n"), ("optical", "o.cx", "o.cy", "o.cz"), ("uv", "u.cx", "u.cy", "u.cz")))
SQL |= {
    "wedge_bounds": f"WITH {ctes('optical', f=FULL)} SELECT 0 AS k, CAST(0 AS DOUBLE) AS ra UNION ALL SELECT 8, 360 UNION ALL " + " UNION ALL ".join(f"SELECT {k}, (SELECT round(quantile_disc(ra, {k / 8}), 6) FROM optical)" for k in range(1, 8)),
    "position_rms": f"WITH q AS ({two_sql(extra=', a.w * a.cx + b.w * b.cx AS x, a.w * a.cy + b.w * b.cy AS y, a.w * a.cz + b.w * b.cz AS z, a.obj AS ao, b.obj AS bo')}), m AS (SELECT *, sqrt(x * x + y * y + z * z) AS n FROM q WHERE ao = bo), {ctes('optical', 'uv')}, t AS ({_TRUE}) SELECT {_RMS} FROM m JOIN optical o ON o.key = m.optical_key JOIN uv u ON u.key = m.uv_key JOIN t ON t.obj = m.ao",
}


def _bound(a: str, b: str, w: float) -> str:
    """The best that a pair can reach with a detection of weight w to come."""
    total = f"sqrt({' + '.join(f'pow({a}.w * {a}.c{k} + {b}.w * {b}.c{k}, 2)' for k in 'xyz')})"
    deficit = f"({a}.w * {b}.w * ({c2(a, b)}) / ({a}.w + {b}.w + {total}))"
    left = f"({a}.w + {b}.w - {deficit})"
    return f"(ln(2 * {a}.w) + ln(2 * {b}.w) - {deficit} - ln(2 * {left}) + ln(2 * {w!r}) + ln({left}) - ln({left} + {w!r}))"


def _rounds_sql() -> str:
    w = {n: (206264.80624709636 / (ERRORS[n] * 60)) ** 2 for n in ERRORS}
    first = lambda a, b, c: f"(SELECT count(*) FROM ({near('a', 'b', a, b, 600.0)}) p JOIN {a} a ON a.key = p.a_key JOIN {b} b ON b.key = p.b_key WHERE {_bound('a', 'b', w[c])} >= ln(1000.0) - 1e-9)"
    rows = [("listed", first("optical", "uv", "nir")), ("reversed", first("nir", "uv", "optical"))]
    body = " UNION ALL ".join(f"SELECT '{o}' AS plan_order, CAST(0 AS INT) AS round, {n} AS kept UNION ALL SELECT '{o}', 1, (SELECT count(*) FROM full3)" for o, n in rows)
    return f"WITH {_triples(CROWD60, 1e3)} {body}"


def _ratio_sql() -> str:
    one = lambda k: f"SELECT CAST({k} AS DOUBLE) AS factor, (SELECT count(*) FROM optical) * (SELECT count(*) FROM uv) AS product, count(*) AS kept, true AS selective FROM ({near('a', 'b', 'optical', 'uv', max(20.0, 5 * k))}) p JOIN optical a ON a.key = p.a_key JOIN uv b ON b.key = p.b_key WHERE {ln_b('a', 'b')} >= ln(1000.0)"
    return " UNION ALL ".join(f"SELECT * FROM (WITH {ctes('optical', 'uv', f=Field(factor=k))} {one(k)}) f{k:.0f}" for k in (1.0, 10.0, 60.0))


_CUTS = ", ".join(f"near_{n} AS ({near('a', 'b', 'optical', n, 300.0 if n == 'transient' else 20.0)})" for n in ("uv", "nir", "transient"))
_FOUR = f"""WITH {ctes('optical', 'uv', 'nir', 'transient')}, {_CUTS}
SELECT a.key AS optical_key, b.key AS uv_key, c.key AS nir_key, e.key AS transient_key, {place('a', 'b', 'c', 'e')}
FROM near_uv JOIN near_nir USING (a_key) JOIN near_transient USING (a_key) JOIN optical a ON a.key = a_key JOIN uv b ON b.key = near_uv.b_key JOIN nir c ON c.key = near_nir.b_key JOIN transient e ON e.key = near_transient.b_key
WHERE {ln_b('a', 'b', 'c', 'e')} >= ln({LIMIT!r})"""
_COUNT = {n: f"(SELECT count(*) FROM {n})" for n in FILTERS}
_KEPT = {n: f"(SELECT count(*) FROM {n}{f' WHERE {w}' if w else ''})" for n, w in FILTERS.items()}


def _order_sql(how: str, counts: dict[str, str]) -> str:
    rows = " UNION ALL ".join(f"SELECT '{how}' AS how, {k} AS listed, '{n}' AS catalog, CAST({c} AS DOUBLE) AS rows" for k, (n, c) in enumerate(counts.items()))
    return f"SELECT how, CAST(row_number() OVER (ORDER BY rows, listed) - 1 AS INT) AS place, catalog, rows FROM ({rows}) r_{how}"


def _copies_sql() -> str:
    """Border copies at radius 3 arc seconds: zones by cells, counted row by row."""
    out = []
    for h_as in (10.0, 30.0, 300.0):
        h, r = h_as / 3600, 3 / 3600
        worst = f"least(90, greatest(abs(zone * {h!r} - 90), abs(zone * {h!r} - 90 + {h!r})))"
        half = f"degrees(atan2(sin(radians({r!r})), sqrt(cos(radians(dec) - radians({r!r})) * cos(radians(dec) + radians({r!r})))))"
        zones = f"SELECT key, ra, dec, unnest(range(CAST(floor((dec - {r!r} + 90) / {h!r}) AS BIGINT), CAST(floor((dec + {r!r} + 90) / {h!r}) AS BIGINT) + 1)) AS zone FROM optical"
        out.append(f"SELECT CAST({h_as} AS DOUBLE) AS height_as, CAST(sum(least(n, floor((ra + half) * n / 360) - floor((ra - half) * n / 360) + 1)) AS BIGINT) AS copies FROM (SELECT *, greatest(1, floor(360 * cos(radians({worst})) / {h!r})) AS n, {half} AS half FROM ({zones}) z{h_as:.0f}) q{h_as:.0f}")
    return f"WITH {ctes('optical')} " + " UNION ALL ".join(out)


_INSIDE, _OTHER = _circle(180, 0, 1.0), _circle(181, 0.5, 0.75)
SQL |= {
    "match_round_counts": _rounds_sql(),
    "candidate_ratio": _ratio_sql(),
    **dict.fromkeys(("match_four_cascading", "match_four_colocated"), _FOUR),
    "match_cached_zones": two_sql(),
    "match_epochs": f"SELECT optical_key, CAST(year(epoch) AS INT) AS year, count(*) AS n, min(uv_key) AS first_key FROM ({two_sql(extra=', b.epoch AS epoch')}) q GROUP BY 1, 2",
    "match_filtered_order": f"WITH {_triples(FINE, LIMIT)} SELECT optical_key, uv_key, nir_key, t.ra, t.dec, ln_bf FROM full3 t JOIN optical o ON o.key = optical_key JOIN uv u ON u.key = uv_key WHERE o.is_target = 1 AND u.mag < 14",
    "filtered_orders": f"WITH {ctes('optical', 'uv', 'nir')} SELECT * FROM ({_order_sql('static', _COUNT)}) a UNION ALL SELECT * FROM ({_order_sql('estimated', _KEPT)}) b",
    "region_rounds": f"WITH {ctes('optical')}, m AS ({two_sql()}), i AS (SELECT count(*) AS n FROM m JOIN optical o ON o.key = m.optical_key WHERE {_INSIDE}) SELECT 'owner' AS region_on, n AS kept, n AS rows FROM i UNION ALL SELECT 'post', (SELECT count(*) FROM m), n FROM i",
    "region_complement": f"WITH {ctes('optical')} SELECT {_INSIDE} AS a, NOT ({_INSIDE}) AS not_a, NOT ({_INSIDE} OR {_OTHER}) AS none, NOT ({_INSIDE}) AND NOT ({_OTHER}) AS both_out, count(*) AS n FROM optical o GROUP BY ALL",
    "region_areas": f"WITH {ctes('survey_caps')}, c AS (SELECT 2 * pi() * (1 - cos(radians(1))) AS a) SELECT 'circle' AS name, round(a * pow(180 / pi(), 2), 6) AS square_deg FROM c UNION ALL SELECT 'rest', round((4 * pi() - a) * pow(180 / pi(), 2), 6) FROM c UNION ALL SELECT 'caps', round(sum(2 * pi() * (1 - cos(radians(cap_deg)))) * pow(180 / pi(), 2), 6) FROM survey_caps",
    "estimate_q_error": f"SELECT name, round(greatest(estimate, 1.0, actual::DOUBLE) / least(greatest(estimate, 1.0), greatest(actual::DOUBLE, 1.0)), 6) AS q_error FROM ({SQL['cardinality_estimates']}) q",
    "dropout_report": f"SELECT verdict, count(*) AS n FROM ({SQL['dropout_explained']}) q GROUP BY 1",
    "colour_classes": f"WITH {ctes('optical', 'uv', f=CROWD60)}, p AS ({near('a', 'b', 'optical', 'uv', 300.0)}), m AS (SELECT a.mag - b.mag AS colour, {_TOTAL} AS total FROM p JOIN optical a ON a.key = p.a_key JOIN uv b ON b.key = p.b_key WHERE {ln_b('a', 'b')} >= ln(1000.0)) SELECT CASE WHEN colour > {COLOUR!r} THEN 'star' ELSE 'quasar' END AS class, count(*) AS n, count(*) FILTER (WHERE total >= ln(1000.0)) AS kept FROM m GROUP BY 1",
    "mini_documents": f"SELECT 'documents' AS name, count(*) AS n FROM documents WHERE {_chosen('doc_id', 0.2)} UNION ALL SELECT 'labels', count(*) FROM labels WHERE doc_id IN (SELECT doc_id FROM documents WHERE {_chosen('doc_id', 0.2)})",
    "replication_factor": _copies_sql(),
    "match_text_or": f"SELECT optical_key, uv_key FROM ({two_sql(where=' AND (a.is_target = 1 AND a.mag < 19 OR b.mag < 15)')}) q",
    "match_text_joins": f"SELECT optical_key, uv_key, n_name AS nation, copy FROM ({two_sql(extra=', a.c_nationkey, a.mag AS m, a.is_target AS t')}) q JOIN nation ON n_nationkey = c_nationkey, (SELECT unnest([0, 1])::BIGINT AS copy) k WHERE m < 19 AND uv_key < (SELECT avg(o_orderkey) FROM orders) AND CASE WHEN t = 1 AND m > 17 THEN true ELSE m < 18 END",
}
