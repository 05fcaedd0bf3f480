import time

import pytest
from pyspark.sql import functions as F

from skyjoin import workloads as w
from skyjoin.operators.regions import RegionStore, parse_region
from skyjoin.plans import jobs
from skyjoin.plans.language import QueryError, parse, sky_sql, split, top_level
from skyjoin.plans.stats import Estimate, estimate, wedges
from skyjoin.sources.catalogs import CatalogRegistry, Meta, UserSpace, ZoneCache, describe, metadata_of, provenance
from skyjoin.sources.skyfix import FULL, catalog

HEAD = "SELECT x.ra, s.key FROM d.optical AS s, d.uv AS t WHERE s.is_target = 1 AND t.mag < 30 AND s.mag BETWEEN 1 AND 99 AND (s.key > 0 OR t.key > 0) "
CLAUSE = "CROSSMATCH USING bayes AS x (REQUIRE s AT XYZ(cx, cy, cz) ERROR 0.1, ALLOW t AT SKY(ra, dec) ERROR sigma_as * 1.0 PREFILTER mag < 90) EVIDENCE >= 1e6"


def test_parse_and_split():
    q = parse(HEAD + CLAUSE + " WITHIN 'circle J2000 180 0 60' INTO u.r;")
    assert [m.alias for m in q.members] == ["s", "t"] and q.limit == 1e6 and q.region == "circle J2000 180 0 60" and q.into == "u.r"
    down, up = split(q)
    assert down == {"s": ["is_target = 1", "mag BETWEEN 1 AND 99"]}
    assert up == ["t.mag < 30", "(s.key > 0 OR t.key > 0)"]
    assert top_level("a, f(b, c), 'd, e'", ",") == ["a", "f(b, c)", "'d, e'"]


@pytest.mark.parametrize(
    "text",
    [
        HEAD + CLAUSE.replace(" EVIDENCE >= 1e6", ""),
        HEAD + CLAUSE.replace("bayes", "nearest"),
        HEAD + CLAUSE + " WITHIN 'circle 0 0 1' WITHIN 'circle 0 0 1'",
        HEAD + CLAUSE + " WITHIN 'circle 0 0 1' OR 1 = 1",
        HEAD + CLAUSE.replace("REQUIRE s", "REQUIRE z"),
        HEAD + CLAUSE.replace("XYZ(cx, cy, cz)", "XYZ(cx, cy)"),
        "SELECT (SELECT 1 CROSSMATCH USING bayes AS x (REQUIRE s AT SKY(a, b) ERROR 1) EVIDENCE >= 1) FROM s",
    ],
)
def test_syntax_errors(text):
    with pytest.raises(QueryError):
        parse(text)


def test_conditions_of_any_form():
    q = parse("SELECT s.key FROM d.optical AS s CROSS JOIN d.uv AS t JOIN d.n AS n ON n.id = s.nation AND s.mag < 3 WHERE s.a = 1 AND s.b = 2 OR t.c = 3 " + CLAUSE)
    assert q.sources == (("d.optical", "s"), ("d.uv", "t")) and q.joins == "JOIN d.n AS n ON true"
    assert split(q) == ({"s": ["mag < 3"]}, ["s.a = 1 AND s.b = 2 OR t.c = 3", "n.id = s.nation"])
    q = parse("SELECT s.key FROM d.optical AS s JOIN d.uv AS t ON s.mag < t.mag AND s.k = 1 WHERE CASE WHEN s.a = 1 AND s.b = 2 THEN true ELSE false END AND free > 1 AND abs(s.c) < 2 " + CLAUSE)
    assert split(q) == ({"s": ["CASE WHEN a = 1 AND b = 2 THEN true ELSE false END", "abs(c) < 2", "k = 1"]}, ["free > 1", "s.mag < t.mag"])
    with pytest.raises(QueryError):
        parse("SELECT s.key FROM d.optical AS s LEFT JOIN d.uv AS t ON s.mag < t.mag " + CLAUSE)


def test_keys_are_checked_and_results_recorded(spark, sf):
    from skyjoin.plans.resolve import ResolveError

    tables = {f"d.{n}": catalog(spark, sf, n) for n in ("optical", "uv")}
    text = "SELECT s.key, x.ra FROM d.optical AS s, d.uv AS t " + CLAUSE.replace("ALLOW", "REQUIRE").replace(" PREFILTER mag < 90", "")
    with pytest.raises(ResolveError):
        sky_sql(spark, text, tables | {"d.uv": tables["d.uv"].unionAll(tables["d.uv"])}, keys=1.0)
    assert sky_sql(spark, text + " INTO stored_match", tables).count() == 273
    record = spark.sql("SHOW TBLPROPERTIES stored_match").filter("key = 'provenance'").first().value
    assert '"limit": 1000000.0' in record and '"s": "require"' in record and "d.optical" in record


def test_time_out_cancels_a_running_wedge(spark, sf):
    from skyjoin.operators import relational

    job = relational._job(spark, sf, 2, lambda k, step: relational.slowed(step(k), 60.0))
    began = time.time()
    with pytest.raises(TimeoutError):
        jobs.submit(job, "quick", {"quick": 3.0})
    assert time.time() - began < 45 and not job.done()
    job = relational._job(spark, sf, 2)
    assert jobs.submit(job, "long").count() == 273


def test_late_rows_are_left_out(spark, tmp_path):
    """Rows that come two micro-batches after the watermark has passed their window."""
    from skyjoin.streaming import alerts

    folder = tmp_path / "late"
    for k, rows in enumerate(([(1, "2026-01-01 00:10:00", "a", 1.0)], [(2, "2026-01-01 09:00:00", "a", 1.0)], [(6, "2026-01-01 09:10:00", "a", 1.0)], [(3, "2026-01-01 00:20:00", "a", 1.0), (4, "2026-01-01 08:30:00", "a", 1.0)], [(5, "2026-01-02 00:00:00", "a", 1.0)])):
        df = spark.createDataFrame(rows, "event_id long, t string, event_type string, value double").selectExpr("event_id", "cast(t AS timestamp) AS ts", "event_type", "value")
        df.coalesce(1).write.mode("append").parquet(str(folder))
        time.sleep(1.1)
    stream = alerts.read_events(spark, f"{folder}/*.parquet")
    got = alerts.drained(alerts.windowed(stream, "ts", "event_type", "1 hour"), "late")
    rows = {str(r.window.start)[11:13]: r.n for r in got.collect()}
    assert rows["00"] == 1 and rows["08"] == 1 and rows["09"] == 2


def test_query_text_runs(spark, sf):
    tables = {f"d.{n}": catalog(spark, sf, n) for n in ("optical", "uv")}
    out = sky_sql(spark, HEAD.replace("t.mag < 30", "coalesce(t.mag, 0) < 30") + CLAUSE, tables)
    assert out.columns == ["ra", "key"] and out.count() > 0
    side = sky_sql(spark, "SELECT s.c_nationkey AS n, count(*) AS k FROM d.optical AS s, d.uv AS t GROUP BY s.c_nationkey " + CLAUSE.replace("ALLOW", "REQUIRE").replace(" PREFILTER mag < 90", ""), tables)
    assert side.agg(F.sum("k")).first()[0] == 273
    plain = "SELECT count(*) AS n FROM range(5) WHERE 'CROSSMATCH' = 'CROSSMATCH'"
    assert sky_sql(spark, plain).first().n == 5


def test_job_retries_resumes_and_cleans(spark, tmp_path):
    seen: dict[int, int] = {}

    def step(k):
        seen[k] = seen.get(k, 0) + 1
        if k == 2 and seen[k] == 1:
            raise RuntimeError("injected")
        return spark.range(k * 10, k * 10 + 10)

    job = jobs.Job(spark, str(tmp_path), step, 4)
    job._one(0)
    assert job.run().count() == 40 and seen == {0: 1, 1: 1, 2: 2, 3: 1} and job.redone == 1
    assert job.resume().count() == 40 and seen[0] == 1
    with pytest.raises(jobs.Failed):
        jobs.Job(spark, str(tmp_path), step, 4, job_id=job.job_id, version=2).run()
    job.cleanup()
    assert not (tmp_path / f"job-{job.job_id}").exists()

    def broken(k):
        raise RuntimeError("always")

    bad = jobs.Job(spark, str(tmp_path), broken, 2, retries=1)
    with pytest.raises(jobs.Failed):
        bad.run()
    assert not (tmp_path / f"job-{bad.job_id}").exists()
    slow = jobs.Job(spark, str(tmp_path), step, 3)
    slow.suspended.set()
    with pytest.raises(jobs.Suspended):
        slow.run()
    assert slow.resume().count() == 30


def test_assignment_and_replication():
    costs = [5.0, 1.0, 1.0, 1.0, 4.0, 1.0]
    assert jobs.makespan(costs, jobs.balanced(costs, 2)) <= jobs.makespan(costs, jobs.round_robin(6, 2))
    assert jobs.replicate_plan(1) == [] and [len(r) for r in jobs.replicate_plan(6)] == [1, 2, 2]


def test_wedges_and_estimates(spark, sf):
    c = catalog(spark, sf, "uv", FULL)
    bounds = wedges(c, 5)
    assert bounds[0] == 0 and bounds[-1] == 360 and bounds == sorted(bounds)
    assert sum(jobs.anchor_slice(c, bounds, k).count() for k in range(len(bounds) - 1)) == c.count()
    e = estimate(c, 1.0)
    assert e == Estimate(c.count(), 0.0)


def test_catalogs(spark, sf, tmp_path):
    df = describe(spark.range(3).withColumn("ra", F.lit(1.0)), {"ra": Meta("pos.eq.ra", "deg", "right ascension")})
    df.write.parquet(str(tmp_path / "m"))
    assert metadata_of(spark.read.parquet(str(tmp_path / "m")))["ra"]["unit"] == "deg"
    r = CatalogRegistry(spark)
    r.add("o", f"{sf}/orders.parquet")
    assert r.table("o").count() == 1500
    with pytest.raises(ValueError):
        r.add("c", "x.csv", "csv")
        r.table("c")
    u = UserSpace(spark, "ann")
    u.put("t", df, provenance(["o"], 1e6, {"o": "require"}))
    assert u.get("t").count() == 3 and "require" in u.record("t")
    u.export("t", str(tmp_path / "x"), "csv")
    u.drop("t")
    from skyjoin.operators.zones import Grid

    cache = ZoneCache(spark, buckets=4)
    a = cache.get_or_build("optical", "1", catalog(spark, sf, "optical").select("key", "ra", "dec"), ("ra", "dec"), Grid(0.1))
    b = cache.get_or_build("optical", "1", spark.range(0).toDF("key"), ("ra", "dec"), Grid(0.1))
    assert a.count() == b.count() == 150
    store = RegionStore(spark, "regions_here")
    store.save("mine", parse_region("circle 180 0 60"))
    assert parse_region("stored(mine)", store) == parse_region("circle 180 0 60")


def test_streams_equal_batch(spark, sf):
    from skyjoin.streaming import alerts

    events = alerts.read_events(spark, f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    got = alerts.drained(alerts.without_repeats(events, "event_id", "ts"), "once")
    assert got.count() == spark.read.parquet(f"{sf}/events.parquet").count()
    late = alerts.windowed(events, "ts", "event_type", "1 day")
    assert alerts.drained(late, "windows", "update").count() > 0
    pairs = alerts.stream_pairs(events.select("event_id", "user_id", "ts"), alerts.read_events(spark, f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")).select("event_id", "user_id", "ts"), "user_id", 600)
    assert alerts.drained(pairs, "pairs").filter("a_event_id = b_event_id").count() == 1000


def test_entry_points_have_sql():
    """Costs alone have no SQL: bytes and seconds differ from run to run."""
    assert set(w.QUERIES) - set(w.SQL) == {"experiment_costs"} and set(w.SQL) <= set(w.QUERIES)
