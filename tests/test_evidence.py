import itertools
import math
import random
from decimal import Decimal, getcontext

import numpy as np
import pytest
from pyspark.sql import functions as F

from skyjoin.functions import evidence as e
from skyjoin.functions.sphere import PER_RADIAN
from skyjoin.operators.match import REQUIRE, Participant, match_all

getcontext().prec = 60


def unit(rng, around=(1.0, 0.0, 0.0), spread=1.0):
    v = np.array(around) + spread * np.array([rng.gauss(0, 1) for _ in range(3)])
    return v / np.linalg.norm(v)


def exact(ws, xs):
    """ln B with 60 digits."""
    w = [Decimal(repr(k)) for k in ws]
    x = [[Decimal(repr(float(c))) for c in v] for v in xs]
    x = [[c / sum(k * k for k in v).sqrt() for c in v] for v in x]
    a = [sum(w[i] * x[i][k] for i in range(len(w))) for k in range(3)]
    n = sum(k * k for k in a).sqrt()

    def ln_sinh(v):
        return v - Decimal(2).ln() + (1 - (-2 * v).exp()).ln() if v < 2000 else v - Decimal(2).ln()

    return float(ln_sinh(n) - n.ln() + sum(k.ln() - ln_sinh(k) for k in w))


def state(spark, ws, xs):
    """ln B by merging one detection at a time with the column expressions."""
    a, big, d, s = np.zeros(3), 0.0, 0.0, 0.0
    rows = None
    for w, x in zip(ws, xs, strict=True):
        row = spark.createDataFrame([(float(w), *map(float, x))], "w double, x double, y double, z double")
        one = row.select((F.col("w") * F.col("x")).alias("ax"), (F.col("w") * F.col("y")).alias("ay"), (F.col("w") * F.col("z")).alias("az"), F.lit(0.0).alias("d"), e.ln_term("w").alias("s")).first()
        if rows is None:
            a, d, s = np.array(one[:3]), one.d, one.s
            rows = True
            continue
        n1, n2 = np.linalg.norm(a), np.linalg.norm(one[:3])
        c2 = float(((a / n1 - np.array(one[:3]) / n2) ** 2).sum())
        total = a + np.array(one[:3])
        d = spark.range(1).select(e.merged_deficit(F.lit(d), F.lit(n1), F.lit(0.0), F.lit(n2), F.lit(c2), F.lit(float(np.linalg.norm(total)))).alias("d")).first().d
        a, s = total, s + one.s
    return spark.range(1).select(e.ln_bayes(F.lit(d), F.lit(float(np.linalg.norm(a))), F.lit(s)).alias("b")).first().b


@pytest.mark.parametrize("scale", [0.3, 5.0, 1e4, 4e12])
def test_against_high_precision(spark, scale):
    rng = random.Random(7)
    ws = [scale * rng.uniform(0.5, 2) for _ in range(3)]
    xs = [unit(rng, spread=1 / math.sqrt(scale)) for _ in range(3)]
    want = exact(ws, xs)
    for order in itertools.permutations(range(3)):
        got = state(spark, [ws[i] for i in order], [xs[i] for i in order])
        assert got == pytest.approx(want, rel=1e-5, abs=2e-3)


def test_against_quadrature(spark):
    rng = random.Random(1)
    ws, xs = [3.0, 5.0, 8.0], [unit(rng) for _ in range(3)]
    n = 800
    z = (np.arange(n) + 0.5) / n * 2 - 1
    a = (np.arange(2 * n) + 0.5) / n * math.pi
    s = np.sqrt(1 - z * z)[:, None]
    m = np.stack([s * np.cos(a), s * np.sin(a), np.broadcast_to(z[:, None], (n, 2 * n))])
    same = np.ones((n, 2 * n))
    for w, x in zip(ws, xs, strict=True):
        same = same * w / (4 * math.pi * math.sinh(w)) * np.exp(w * np.tensordot(x, m, 1))
    ln_b = math.log(same.mean()) - 3 * math.log(1 / (4 * math.pi))
    assert state(spark, ws, xs) == pytest.approx(ln_b, abs=1e-4)


def test_limits_of_the_closed_form(spark):
    row = spark.range(1).select(
        e.ln_bayes_flat(F.lit(0.0), F.lit(e.weight_of(0.1)), F.lit(e.weight_of(0.2))).alias("flat"),
        e.ln_bayes(F.lit(0.0), F.lit(5.0), e.ln_term(F.lit(5.0))).alias("one"),
        e.ln_bayes_naive([F.lit(3.0), F.lit(5.0)], F.lit(8.0)).alias("naive"),
        e.ln_bayes(F.lit(0.0), F.lit(8.0), e.ln_term(F.lit(3.0)) + e.ln_term(F.lit(5.0))).alias("stable"),
    ).first()
    assert row.flat == pytest.approx(28.16271, abs=1e-4)
    assert row.one == pytest.approx(0.0, abs=1e-12)
    assert row.naive == pytest.approx(row.stable, abs=1e-12)


def test_search_radius_anchors():
    for a, b, want in ((0.1, 0.2, 1.198), (0.1, 0.5, 2.570), (0.2, 0.5, 2.702)):
        w = [(e.weight_of(x),) * 2 for x in (a, b)]
        assert e.search_chord([w[0]], [w[1]], [], math.log(1e6)) * PER_RADIAN == pytest.approx(want, abs=2e-3)
    assert e.search_chord([(1e3, 1e3)], [(1e3, 1e3)], [], math.log(1e9)) == 0.0


def test_pruning_never_loses(spark):
    """Every triple that all-pairs arithmetic accepts comes out of the zone plan, in crowded low-evidence fields too."""
    rng = random.Random(3)
    for errors, limit in (((60.0, 120.0, 300.0), 10.0), ((7200.0, 3600.0, 18000.0), 1.5)):
        cats = []
        for k, s in enumerate(errors):
            rows = []
            for i in range(25):
                ra, dec = 180 + rng.gauss(0, 2 * s / 3600), rng.gauss(0, 2 * s / 3600)
                rows.append((i + 100 * k, ra, dec))
            cats.append(rows)
        frames = [Participant(n, spark.createDataFrame(rows, "key long, ra double, dec double"), REQUIRE, error=s) for n, rows, s in zip("abc", cats, errors, strict=True)]
        got = {(r.a.key, r.b.key, r.c.key) for r in match_all(frames, limit).collect()}
        back = {(r.a.key, r.b.key, r.c.key) for r in match_all(frames, limit, plan="cascading", order="reversed").collect()}
        want = set()

        def xyz(ra, dec):
            a, d = math.radians(ra), math.radians(dec)
            return np.array([math.cos(d) * math.cos(a), math.cos(d) * math.sin(a), math.sin(d)])

        ws = [e.weight_of(s) for s in errors]
        for trio in itertools.product(*cats):
            x = [xyz(*t[1:]) for t in trio]
            total = sum(ws)
            n = np.linalg.norm(sum(w * v for w, v in zip(ws, x, strict=True)))
            gap = sum(ws[i] * ws[j] * ((x[i] - x[j]) ** 2).sum() for i in range(3) for j in range(i)) / (total + n)
            b = -gap + sum(math.log(2 * w) - math.log1p(-math.exp(-2 * w)) for w in ws) - math.log(2 * n) + math.log1p(-math.exp(-2 * n))
            if b >= math.log(limit):
                want.add(tuple(t[0] for t in trio))
        assert want and got == want == back


def test_posterior_and_property(spark):
    df = spark.createDataFrame([(20.0,), (5.0,), (-3.0,)], "b double")
    rows = [r.posterior for r in e.with_posterior(df, "b", [100.0, 100.0], rounds=3).collect()]
    assert rows == sorted(rows, reverse=True) and all(0 <= p <= 1 for p in rows)
    near, far = spark.range(1).select(e.ln_gaussian_property(F.lit(0.0), F.lit(0.1), F.lit(0.0), F.lit(0.1), 2.0).alias("n"), e.ln_gaussian_property(F.lit(0.0), F.lit(0.1), F.lit(3.0), F.lit(0.1), 2.0).alias("f")).first()
    assert near > 0 > far
    classes = {r.c for r in df.select(e.evidence_class("b").alias("c")).collect()}
    assert classes == {"match", "undecided"}
