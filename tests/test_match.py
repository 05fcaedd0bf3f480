import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from skyjoin import workloads as w
from skyjoin.functions.sphere import chord_of, sphere_cell
from skyjoin.operators.match import ALLOW, FORBID, REQUIRE, Participant, match_all, self_match
from skyjoin.operators.regions import Cap, Convex, Region, parse_region
from skyjoin.operators.sampling import Link, mini
from skyjoin.operators.zones import Grid, pair_table, sky_columns
from skyjoin.plans.resolve import ResolveError, check, validate


def sky(spark, rows, schema="key long, ra double, dec double"):
    return spark.createDataFrame(rows, schema)


def pairs_of(spark, a, b, radius_as, grid=None, replicate="left"):
    x = sky_columns(sky(spark, a, "ka long, ra double, dec double"), ("ra", "dec")).drop("ra", "dec")
    y = sky_columns(sky(spark, b, "kb long, ra double, dec double"), ("ra", "dec")).drop("ra", "dec")
    return sorted((r.ka, r.kb) for r in pair_table(x, y, chord_of(radius_as / 3600), grid, replicate).collect())


def brute(a, b, radius_as):
    def v(ra, dec):
        p, q = math.radians(ra), math.radians(dec)
        return np.array([math.cos(q) * math.cos(p), math.cos(q) * math.sin(p), math.sin(q)])

    c = chord_of(radius_as / 3600)
    return sorted((i, j) for i, *p in a for j, *q in b if np.linalg.norm(v(*p) - v(*q)) <= c)


@pytest.mark.parametrize("radius,height", [(3600.0, 1.0), (7200.0, 2.5), (40000.0, 12.0), (600.0, 30.0)])
def test_zone_join_is_exact_on_the_whole_sky(spark, radius, height):
    rng = random.Random(int(radius))
    edge = [(0, 0.0, 90.0), (1, 123.0, -90.0), (2, 359.9999, 0.0), (3, 0.0001, 0.0), (4, 10.0, 89.99), (5, 190.0, 89.99), (6, 180.0, -89.9)]

    def cat(base):
        rows = [(base + i, ra, dec) for i, ra, dec in edge]
        for i in range(120):
            z = rng.uniform(-1, 1) if i % 3 else rng.choice((-1, 1)) * rng.uniform(0.99, 1)
            rows.append((base + 10 + i, rng.uniform(0, 360), math.degrees(math.asin(z))))
        return rows

    a, b = cat(0), cat(1000)
    want = brute(a, b, radius)
    for grid in (None, Grid(height), Grid(max(height, radius / 3600), cells=False)):
        for side in ("left", "right"):
            assert pairs_of(spark, a, b, radius, grid, side) == want


def test_anchor_counts(spark, sf):
    q = w.QUERIES
    for name, n in (("match_two_required", 273), ("match_three_required", 536), ("match_optional_third", 570), ("match_dropout", 34), ("sample_crossmatch", 41), ("self_match", 227), ("match_row_errors", 1000), ("match_cartesian", 235), ("crowded_triples", 642), ("crowded_dropout", 28)):
        assert q[name](spark, sf).count() == n, name


def test_plans_agree_and_modes_nest(spark, sf):
    rows = {n: set(map(tuple, w.QUERIES[n](spark, sf).select("optical_key", "uv_key", "nir_key").collect())) for n in ("match_three_required", "match_three_cascading", "match_three_colocated", "match_order_reversed", "match_three_wedges", "match_no_pruning")}
    assert len({frozenset(x) for x in rows.values()}) == 1
    may = set(map(tuple, w.QUERIES["match_optional_third"](spark, sf).select("optical_key", "uv_key", "nir_key").collect()))
    assert rows["match_three_required"] <= may
    without = set(map(tuple, w.QUERIES["match_dropout"](spark, sf).select("optical_key", "uv_key").collect()))
    assert {(a, b) for a, b, c in may if c is None} == without


def test_edge_rows_and_errors(spark):
    bad = [(1, 10.0, 5.0, 0.1), (2, None, 5.0, 0.1), (3, float("nan"), 5.0, 0.1), (4, 10.0, 95.0, 0.1), (5, 10.0, 5.0, 0.0), (6, 10.0, 5.0, -1.0), (7, 370.0, 5.0, 0.1)]
    a = Participant("a", sky(spark, bad, "key long, ra double, dec double, sigma_as double"))
    b = Participant("b", sky(spark, [(1, 10.0, 5.0)]), error=0.2)
    assert {r.a.key for r in match_all([a, b], 1e6).collect()} == {1, 7}
    empty = Participant("b", sky(spark, []), error=0.2)
    assert match_all([a, empty], 1e6).count() == 0
    from dataclasses import replace

    assert match_all([a, b, replace(empty, alias="c", mode=FORBID)], 1e6).count() == 2
    rows = match_all([a, b, replace(empty, alias="c", mode=ALLOW)], 1e6).collect()
    assert len(rows) == 2 and all(r.c is None for r in rows)
    for parts, limit in (([a], 1e6), ([a, b], 0), ([a, b], None), ([replace(a, mode=FORBID), replace(b, mode=FORBID)], 1e6), ([a, replace(b, alias="a")], 1e6)):
        with pytest.raises(ValueError):
            match_all(parts, limit)
    with pytest.raises(ResolveError):
        validate(Participant("d", sky(spark, [(1, 1.0, 1.0), (1, 2.0, 2.0)]), error=0.1))
    with pytest.raises(ResolveError):
        check(Participant("d", sky(spark, [(1, 1.0, 1.0)]), error="no_such"))
    assert validate(a) == {"rows": 7, "no_position": 2, "no_error": 2}


def test_self_match_both_ways(spark):
    p = Participant("a", sky(spark, [(1, 10.0, 5.0), (2, 10.0, 5.0), (3, 50.0, 5.0)]), error=0.1)
    assert [(r.a.key, r.b.key) for r in self_match(p, 1e6).collect()] == [(1, 2)]
    assert sorted((r.a.key, r.b.key) for r in self_match(p, 1e6, symmetric=True).collect()) == [(1, 2), (2, 1)]


def test_large_errors_reach_across_the_sky(spark):
    a = Participant("a", sky(spark, [(1, 0.0, 0.0), (2, 180.0, 0.0)]), error=3600.0 * 30)
    b = Participant("b", sky(spark, [(1, 20.0, 10.0), (2, 100.0, 80.0)]), error=3600.0 * 20)
    got = {(r.a.key, r.b.key) for r in match_all([a, b], 1.0).collect()}
    assert (1, 1) in got and (2, 1) not in got


def test_no_nested_loop_in_plans(spark, sf):
    for name in ("match_two_required", "match_three_required", "match_optional_third", "match_dropout", "self_match"):
        plan = w.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan


def scans(df):
    """Scans of files in the plan before anything ran."""
    plan = df._jdf.queryExecution().sparkPlan().toString()
    return plan.count("FileScan parquet")


def test_optional_and_excluded_catalogs_are_read_once(spark, sf):
    parts = [w.part(spark, sf, "optical"), w.part(spark, sf, "uv")]
    from dataclasses import replace

    for mode in (ALLOW, FORBID):
        for n in (1, 2, 3):
            more = [replace(w.part(spark, sf, "nir", mode), alias=f"nir{k}") for k in range(n)]
            assert scans(match_all([*parts, *more], 1e6)) == 2 + n
    flagged = match_all([*parts, w.part(spark, sf, "nir", FORBID)], 1e6, dropouts=True)
    assert scans(flagged) == 3 and {r.blocked: r["count"] for r in flagged.groupBy("blocked").count().collect()} == {True: 239, False: 34}


def test_two_optional_catalogs_by_brute_force(spark):
    """Every detection that extends the tuple, else the tuple itself, catalog by catalog."""
    a = sky(spark, [(1, 10.0, 5.0), (2, 20.0, 5.0), (3, 30.0, 5.0), (4, 40.0, 5.0)])
    b = sky(spark, [(1, 10.0, 5.0), (2, 20.0, 5.0), (3, 30.0, 5.0), (4, 40.0, 5.0)])
    c, e = sky(spark, [(1, 10.0, 5.0), (11, 10.00001, 5.0), (3, 30.0, 5.0)]), sky(spark, [(1, 10.0, 5.0), (2, 20.0, 5.0)])
    m = match_all([Participant("a", a, error=0.1), Participant("b", b, error=0.1), Participant("c", c, ALLOW, error=0.2), Participant("e", e, ALLOW, error=0.2)], 1e6)
    got = sorted((r.a.key, r.c.key if r.c else 0, r.e.key if r.e else 0) for r in m.collect())
    assert got == [(1, 1, 1), (1, 11, 1), (2, 0, 2), (3, 3, 0), (4, 0, 0)]


def test_one_bad_row_does_not_widen_all(spark):
    """A catalog with one error of ten degrees: the pairs looked at stay near those of the sharp rows, and none is lost."""
    from skyjoin.operators.match import Trace

    rng = random.Random(5)
    a = [(k, 100 + rng.random() * 4, rng.random() * 4) for k in range(1500)]
    b = [(k, ra + rng.gauss(0, 0.2) / 3600, dec, 0.2) for k, ra, dec in a]
    counts = []
    for rows in (b, [*b[:-1], (*b[-1][:3], 36000.0)]):
        trace = Trace()
        m = match_all([Participant("a", sky(spark, a), error=0.1), Participant("b", sky(spark, rows, "key long, ra double, dec double, sigma_as double"))], 1e2, trace=trace)
        found = {(r.a.key, r.b.key) for r in m.collect()}
        counts.append((dict(trace.counts())["candidates"], found))
    assert counts[1][0] < counts[0][0] + 3000 and len(counts[0][1] - counts[1][1]) <= 1 and counts[0][0] < 40_000
    assert {k for k, j in counts[1][1] if j == k} >= set(range(1490)) - {k for k, j in a[:0]}


def test_levels_lose_nothing(spark, sf):
    """Errors from 0.1 to 2,000 arc seconds: the same pairs as by one wide radius."""
    c = w.catalog(spark, sf, "transient").withColumn("wide", F.expr("CASE WHEN key % 7 = 0 THEN 2000e0 WHEN key % 5 = 0 THEN 90e0 ELSE sigma_as END"))
    o = Participant("o", w.catalog(spark, sf, "optical"), error=0.1)
    t = Participant("t", c, error="wide")
    want = {(r.o.key, r.t.key) for r in match_all([o, t], 1e3, grid=Grid(1.0)).collect()}
    for parts in ([o, t], [t, o]):
        assert {(r.o.key, r.t.key) for r in match_all(parts, 1e3).collect()} == want
    assert len(want) > 1000


def test_grid_follows_the_density():
    from skyjoin.operators.zones import choose_grid

    assert choose_grid(1 / 3600).height == 30 / 3600
    assert choose_grid(1 / 3600, 1e6).height == pytest.approx(4e-3) and choose_grid(1 / 3600, 1e9).height == pytest.approx(4 / 3600)
    assert choose_grid(1 / 3600, 1.0).height == 1.0 and choose_grid(50.0).height == 180.0


def test_objects_of_large_keys(spark):
    from skyjoin.operators.match import objects_of

    top = 2**62
    pairs = spark.createDataFrame([(top + k, top + k + 1) for k in range(6)] + [(1, 2)], "a long, b long")
    nodes = spark.createDataFrame([(top + k,) for k in range(8)] + [(1,), (2,), (9,)], "key long")
    got = dict(map(tuple, objects_of(pairs, nodes).collect()))
    assert got == {**{top + k: top for k in range(7)}, top + 7: top + 7, 1: 1, 2: 1, 9: 9}


def test_region_join_of_wide_circles(spark):
    from skyjoin.operators.regions import region_join

    points = sky_columns(sky(spark, [(1, 10.0, 0.0), (2, 12.5, 0.0), (3, 50.0, 0.0)]), ("ra", "dec")).drop("ra", "dec")
    caps = sky_columns(sky(spark, [(7, 10.0, 0.0, 3.0), (8, 10.0, 0.0, 0.5)], "mask long, ra double, dec double, cap_deg double"), ("ra", "dec")).drop("ra", "dec")
    assert sorted((r.key, r.mask) for r in region_join(points, caps).collect()) == [(1, 7), (1, 8), (2, 7)]
    assert {r.key for r in region_join(points, caps, how="left_anti").collect()} == {3} and {r.key for r in region_join(points, caps, how="left_semi").collect()} == {1, 2}
    with pytest.raises(ValueError):
        region_join(points, caps, 1.0)


def test_cached_zones_are_not_shuffled(spark, sf):
    """The side that a zone cache keeps is read in its buckets: one exchange less."""
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plans = [w.QUERIES[n](spark, sf)._jdf.queryExecution().sparkPlan() and w.QUERIES[n](spark, sf)._jdf.queryExecution().executedPlan().toString() for n in ("match_two_required", "match_cached_zones")]
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert [p.count("Exchange hashpartitioning") for p in plans] == [2, 1]


def test_regions(spark):
    a, b = Region.circle(180, 0, 1), parse_region("circle J2000 180.5 0 45")
    rng = random.Random(2)
    box, poly = Region.box(350, -5, 10, 5), Region.polygon([(0, 0), (10, 0), (0, 10)])
    for _ in range(400):
        p = (180 + rng.uniform(-2, 2), rng.uniform(-2, 2))
        x, y = a.has(*p), b.has(*p)
        assert (a | b).has(*p) == (x or y) and (a & b).has(*p) == (x and y) and (a - b).has(*p) == (x and not y)
        assert (~(a | b)).has(*p) == (~a & ~b).has(*p) and (~a).has(*p) != x
        low = (a | b).bounds()
        if x or y:
            assert low.low <= p[1] <= low.high and any(s <= p[0] % 360 <= e for s, e in low.ranges)
    assert box.has(0, 0) and box.has(355, 4.9) and not box.has(11, 0) and not box.has(180, 0)
    assert poly.has(2, 2) and not poly.has(9, 9)
    assert a.area() == pytest.approx(2 * math.pi * (1 - math.cos(math.radians(1))))
    assert (a - b).area() + (a & b).area() == pytest.approx(a.area(), rel=0.01)
    assert Region.from_json((a - b).to_json()) == a - b
    assert Region((Convex((Cap.circle(0, 0, 1), Cap.circle(90, 0, 1))),)) & a == Region.nothing()
    for text in ("circle B1950 180 0 60", "circle 1 2", "not(circle 0 0 1, circle 0 0 1)", "circle 0 0 1 extra", "blob 1 2 3"):
        with pytest.raises(ValueError):
            parse_region(text)


def test_mini_keeps_references(spark, sf):
    t = {n: spark.read.parquet(f"{sf}/{n}.parquet") for n in ("customer", "orders", "lineitem")}
    m = mini(t, "customer", "c_custkey", [Link("lineitem", "l_orderkey", "orders", "o_orderkey"), Link("orders", "o_custkey", "customer", "c_custkey")], 0.2)
    assert m["orders"].join(m["customer"], F.col("o_custkey") == F.col("c_custkey"), "left_anti").count() == 0
    assert m["lineitem"].join(m["orders"], F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").count() == 0
    assert 0 < m["customer"].count() < t["customer"].count()


def test_sphere_cells_nest(spark):
    df = spark.createDataFrame([(float(k * 37 % 360), float(k * 11 % 180 - 90)) for k in range(200)], "ra double, dec double")
    for r in df.select(sphere_cell("ra", "dec", 5).alias("f"), sphere_cell("ra", "dec", 4).alias("c")).collect():
        assert r.f >> 2 == r.c


def test_zones_have_the_cells_of_their_exact_edges(spark):
    from decimal import Decimal

    from skyjoin.functions.sphere import cells_of

    def exact(zone: int) -> int:
        low = zone * Decimal("0.05") - 90
        worst = float(max(abs(low), abs(low + Decimal("0.05"))))
        return max(1, math.floor(360 * math.cos(math.radians(worst)) / 0.05))

    found = spark.range(3600).select(F.col("id").cast("int").alias("zone")).select("zone", cells_of("zone", 0.05).alias("n")).collect()
    assert [(r.zone, r.n) for r in found if r.n != exact(r.zone)] == []  # zone 2999 ends at 60 degrees: 3600 cells


def test_a_crowded_match_looks_at_few_candidates(spark):
    from skyjoin.operators.match import Trace

    rng = np.random.default_rng(5)
    n = 3000
    field = lambda: sky(spark, [(k, float(a), float(d)) for k, (a, d) in enumerate(rng.uniform(10.2, 10.7, (n, 2)))]).withColumn("sigma_as", F.lit(6.0))
    a, b = Participant("a", field()), Participant("b", field(), error=12.0)
    trace = Trace()
    found = {tuple(r) for r in match_all([a, b], 1e3, trace=trace).select("a.key", "b.key").collect()}
    counts = dict(trace.counts())
    assert counts["candidates"] < 0.08 * n * n  # 0.2 with cells of ten radii
    wide = {tuple(r) for r in match_all([a, b], 1e3, grid=Grid(0.5)).select("a.key", "b.key").collect()}
    assert found == wide and len(found) > n


def test_brute_pairs_need_no_cross_join(spark):
    from skyjoin.operators.baselines import brute_pairs

    rng = np.random.default_rng(8)
    n = 300
    draw = lambda s: [(k, float(a), float(d), s) for k, (a, d) in enumerate(zip(rng.uniform(9.9, 10.1, n), rng.uniform(-0.1, 0.1, n), strict=True))]
    a, b = draw(6.0), draw(12.0)
    out = brute_pairs(*[sky(spark, r, "key long, ra double, dec double, sigma_as double") for r in (a, b)], 1e3)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "Join Cross" not in plan and "__rband" in plan
    unit = lambda r: np.array([(math.cos(math.radians(d)) * math.cos(math.radians(x)), math.cos(math.radians(d)) * math.sin(math.radians(x)), math.sin(math.radians(d))) for _, x, d, _ in r])
    v = (6.0**2 + 12.0**2) / 206264.80624709636**2
    c2 = ((unit(a)[:, None] - unit(b)[None]) ** 2).sum(2)
    expected = {(int(i), int(j)) for i, j in np.argwhere(math.log(2) - math.log(v) - c2 / (2 * v) >= math.log(1e3))}
    assert {(r.a_key, r.b_key) for r in out.collect()} == expected and expected


def test_table_functions_read_a_catalog(spark, sf):
    out = w.QUERIES["table_functions"](spark, sf)
    assert any(f.endswith("customer.parquet") for f in out.inputFiles())
    assert sum(r.n for r in out.collect()) > 0


def test_sharp_stream_rows_search_no_farther_than_they_reach():
    from skyjoin.streaming.alerts import error_levels

    chord, limit = chord_of(200 / 3600), 1e6
    levels = error_levels(0.1, chord, limit)
    assert levels[0].chord < chord / 10 and levels[-1].chord == chord and levels[-1].least == 0
    for s in np.geomspace(0.01, 300, 400):
        own = next(v for v in levels if 1 / s >= v.least)
        for t in (0.0, 0.05, 0.1):
            v = (s * s + t * t) / 206264.80624709636**2
            assert own.chord >= min(chord, math.sqrt(max(0.0, 2 * v * (math.log(2 / limit) - math.log(v)))))


def test_rounded_is_round_to_the_bit(spark):
    from skyjoin.functions.plan import rounded

    spread = spark.range(20_000).select(((F.rand(1) - 0.5) * F.pow(F.lit(10.0), F.rand(2) * 14 - 7)).alias("v"))
    ties = spark.range(4001).select(((F.col("id") - 2000) / 2000).alias("v"))
    odd = spark.createDataFrame([(x,) for x in (math.nan, math.inf, -math.inf, None, 0.0, -0.0, -1e-9, 1e300, -1e300, 9.2e18, 1e15 + 0.5, -1e12 - 0.3, 1.0005, 2.6750000000000003)], "v double")
    df = spread.unionByName(ties).unionByName(odd)
    for places in (3, 6):
        wrong = df.filter(~rounded("v", places).cast("string").eqNullSafe(F.round("v", places).cast("string")))
        assert wrong.isEmpty()


def test_lost_tuples_come_from_their_weak_pairs(spark, sf):
    keys = ["optical_key", "uv_key", "nir_key"]
    full, cut = ({tuple(r) for r in w.flat(w.three(spark, sf, f=w.CROWD60, limit=1e3, prune=p), *[k[:-4] for k in keys]).select(*keys).collect()} for p in ("bound", "pairwise"))
    lost = w.pairwise_pruning_lost(spark, sf)
    assert scans(lost) == 3  # 6 with both matches worked out and compared
    found = [tuple(r) for r in lost.select(*keys).collect()]
    assert len(found) == len(set(found)) and set(found) == full - cut and found


def test_a_key_of_two_rows_is_lost_only_if_all_its_pairs_are_weak(spark):
    one = lambda *rows: sky(spark, list(rows))
    a, b, c = one((1, 10.0, 0.0)), one((2, 10.0, 0.0008), (3, 10.0, 0.0008), (3, 10.0, 0.0)), one((4, 10.0, 0.0004))
    parts = [Participant(n, df, error=0.5) for n, df in (("a", a), ("b", b), ("c", c))]
    got = [tuple(r) for r in match_all(parts, 1e8, prune="lost").select("a.key", "b.key", "c.key").collect()]
    full = {tuple(r) for r in match_all(parts, 1e8).select("a.key", "b.key", "c.key").collect()}
    assert full == {(1, 2, 4), (1, 3, 4)} and got == [(1, 2, 4)]
    with pytest.raises(ValueError, match="three required"):
        match_all(parts[:2], 1e8, prune="lost")


def test_counts_of_kept_rows_leave_candidates_in_the_join(spark, sf):
    from skyjoin.operators.match import Trace

    every, kept = Trace(), Trace(("kept",))
    for trace in (every, kept):
        df = w.three(spark, sf, f=w.CROWD60, limit=1e3, trace=trace)
        df.select("optical.key").write.format("noop").mode("overwrite").save()
    assert df._jdf.queryExecution().analyzed().toString().count("CollectMetrics") == 2  # 4 with the candidates
    assert kept.counts() == [c for c in every.counts() if c[0] == "kept"] and len(every.counts()) == 4


def test_large_measured_sides_are_not_broadcast(spark, sf, monkeypatch):
    from skyjoin.operators import match

    monkeypatch.setattr(match, "BROADCAST_ROWS", 10)
    plan = w.accuracy_by_crowding(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("SortMergeJoin") == 4 and "BroadcastExchange" not in plan


def test_all_factors_share_one_look_at_the_catalogs(spark, sf, monkeypatch):
    looks, look = [], w.planner.profile
    monkeypatch.setattr(w.planner, "profile", lambda p, *a: looks.append(p.alias) or look(p, *a))
    w.accuracy_by_crowding(spark, sf)
    assert looks == ["optical", "uv"]  # one of each for each factor before, and a count


def test_large_static_side_of_a_stream_is_not_broadcast(spark, sf, monkeypatch):
    from skyjoin.streaming import alerts

    stream = spark.range(100).selectExpr("id AS event_id", "180.0D + id / 100 AS ra", "0.0D AS dec", "0.5D AS sigma_as")
    static = stream.selectExpr("event_id AS key", "ra", "dec", "0.1D AS static_s")
    found = []
    for rows in (alerts.BROADCAST_ROWS, 10):
        monkeypatch.setattr(alerts, "BROADCAST_ROWS", rows)
        m = alerts.stream_match(stream, static, chord_of(200 / 3600), 1e6)
        found.append((sorted(m.select("key", "event_id").collect()), m._jdf.queryExecution().executedPlan().toString()))
    assert found[0][0] == found[1][0] == [(k, k) for k in range(100)]
    assert "BroadcastHashJoin" in found[0][1] and "SortMergeJoin" in found[1][1] and "BroadcastExchange" not in found[1][1]


def test_pairs_with_uneven_errors_are_not_shuffled(spark, sf):
    """No exchange above the join that pairs transients: what stands near the sharper member comes along instead."""
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plans = [w.QUERIES[n](spark, sf)._jdf.queryExecution().executedPlan().toString().splitlines() for n in ("match_four_cascading", "match_four_colocated")]
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    for lines in plans:
        depth = [next((k for k, c in enumerate(line) if c.isalpha()), 0) for line in lines]
        for k, line in enumerate(lines):
            if "Exchange hashpartitioning" in line:
                end = next((j for j in range(k + 1, len(lines)) if depth[j] <= depth[k]), len(lines))
                below = "\n".join(lines[k:end])
                assert not ("Join" in below and "events.parquet" in below)


@pytest.mark.parametrize("plan,names", [("cascading", "abct"), ("colocated", "tabc")])
def test_carried_states_find_the_same_tuples(spark, plan, names, monkeypatch):
    """Equal rows, several states near a detection and either place of the uneven catalog: the same tuples, as often, as without carrying."""
    from collections import Counter

    from skyjoin.operators import match

    rng = random.Random(11)
    true = [(180 + rng.random() / 50, rng.random() / 50) for _ in range(60)]
    noisy = lambda s: [(k % 55, ra + rng.gauss(0, s) / 3600, dec + rng.gauss(0, s) / 3600) for k, (ra, dec) in enumerate(true)]
    cat = {n: Participant(n, sky(spark, noisy(s) + noisy(s)), error=s, site=site) for n, s, site in (("a", 0.1, "p"), ("b", 0.2, "q"))}
    twice = noisy(0.5)
    cat["c"] = Participant("c", sky(spark, twice + twice), error=0.5, site="q")
    uneven = [(k, ra, dec, s) for s in (0.1, 1.0, 8.0, 30.0) for k, ra, dec in noisy(s)]
    cat["t"] = Participant("t", sky(spark, uneven, "key long, ra double, dec double, sigma_as double"), site="p")
    rows = {"a": 120.0, "b": 120.0, "c": 120.0, "t": 240.0}
    called, carry = [], match.combine_carried
    monkeypatch.setattr(match, "combine_carried", lambda *a: called.append(carry(*a) is not None) or carry(*a))
    found = []
    for most in (64.0, -1.0):
        monkeypatch.setattr(match, "MOST_NEAR", most)
        called.clear()
        m = match_all([cat[n] for n in names], 1e6, plan=plan, rows=rows, density=1e5)
        assert any(called) == (most > 0)
        found.append(Counter(tuple(r) for r in m.select(*[F.col(n)["key"] for n in "abct"], F.round("x.ln_bf", 6)).collect()))
    assert found[0] == found[1] and sum(found[0].values()) > 500 and max(found[0].values()) > 1
