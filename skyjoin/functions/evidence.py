"""Evidence that detections share one source: Bayes factors of Fisher-distributed directions, in stable logarithmic form.

A set of detections is a state that adds up: the weighted vector sum, the sum of weights, the deficit of the sum's length
(from chords, never as a difference of large numbers), and the sum of ln G-type terms. States merge in any order.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .sphere import PER_RADIAN, _c


def weight(sigma_as) -> Column:
    """Precision of a 1-D error in arc seconds."""
    return F.lit(PER_RADIAN * PER_RADIAN) / (_c(sigma_as) * _c(sigma_as))


def weight_of(sigma_as: float) -> float:
    return (PER_RADIAN / sigma_as) ** 2


def fisher_ln_pdf(w, c2) -> Column:
    """Logarithm of the density for precision w at a squared chord from the mode (the cosine less one is minus half of it)."""
    w = _c(w)
    return F.log(w) - math.log(2 * math.pi) - F.log1p(-F.exp(-2 * w)) - w * _c(c2) / 2


def ln_term(w) -> Column:
    """What one detection adds to the logarithm: ln 2w less the term that matters at low precision alone."""
    w = _c(w)
    return F.log(2 * w) - F.log1p(-F.exp(-2 * w))


def ln_bayes(deficit, length, terms) -> Column:
    """ln B of a state from its deficit, resultant length and sum of ln_term(). A vanishing resultant has the limit 1."""
    n = _c(length)
    whole = F.log(2 * n) - F.log1p(-F.exp(-2 * n))
    return _c(terms) - _c(deficit) - F.when(n > 1e-12, whole).otherwise(F.lit(0.0))


def ln_bayes_flat(c2, w1, w2) -> Column:
    """The Gaussian limit for two detections of high accuracy."""
    s = 1 / _c(w1) + 1 / _c(w2)
    return math.log(2.0) - F.log(s) - _c(c2) / (2 * s)


def ln_bayes_naive(ws: list, length) -> Column:
    """The product as printed: overflows for every error below about two degrees. A numerical baseline."""
    out = F.sinh(_c(length)) / _c(length)
    for w in ws:
        out = out * (_c(w) / F.sinh(_c(w)))
    return F.log(out)


def merged_deficit(d1, w1, d2, w2, c2, total) -> Column:
    """Deficit of two merged states: lengths w1 and w2, squared chord c2 of their directions, length of their sum."""
    return _c(d1) + _c(d2) + _c(w1) * _c(w2) * _c(c2) / (_c(w1) + _c(w2) + _c(total))


def ln_bound(deficit, weights, terms, rest: list[tuple[float, bool]]) -> Column:
    """The largest ln B that a state can reach with detections still to come, each at no offset with weight (w, required)."""
    left = _c(weights) - _c(deficit)
    value = ln_bayes(deficit, left, terms)
    for w, required in rest:
        gain = math.log(2 * w) - (math.log1p(-math.exp(-2 * w)) if w < 300 else 0.0) + F.log(left) - F.log(left + w)
        value, left = value + (gain if required else F.greatest(F.lit(0.0), gain)), left + w
    return value


def _ln_g(w: float) -> float:
    """ln(sinh w / w)."""
    return w - math.log(2 * w) + (math.log1p(-math.exp(-2 * w)) if w < 300 else 0.0)


def largest_deficit(weights: list[float], ln_limit: float) -> float:
    """The deficit at which detections of these weights just reach the limit; below 0 if they never do."""
    total = sum(weights)
    goal = ln_limit + sum(_ln_g(w) - w for w in weights)  # compared with ln G(total - d) - total

    def value(d: float) -> float:
        left = max(total - d, 1e-300)
        return -d - math.log(2 * left) + (math.log1p(-math.exp(-2 * left)) if left < 300 else 0.0)

    if value(0.0) < goal:
        return -1.0
    low, high = 0.0, min(total, max(1.0, value(0.0) - goal + 2.0))
    while value(high) > goal and high < total:
        high = min(total, 2 * high)
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if value(mid) >= goal else (low, mid)
    return high


def search_chord(prefix: list[tuple[float, float]], new: list[tuple[float, float]], rest: list[float], ln_limit: float) -> float:
    """A chord that no acceptable merge of two states exceeds.

    prefix, new: (least, largest) weight of each member; rest: the largest weights still to come. The most room comes from the
    largest weights, the widest reach from the least.
    """
    room = largest_deficit([h for _, h in prefix] + [h for _, h in new] + rest, ln_limit)
    if room < 0:
        return 0.0
    reach = 0.0
    for side in (prefix, new):
        low = sum(a for a, _ in side)
        # A prefix is shorter than its weights by its own deficit at most.
        reach += 1 / max(low - (room if len(side) > 1 else 0.0), low * 1e-3, 1e-300)
    return min(2.0, math.sqrt(2 * room * reach) * (1 + 1e-9) + 1e-14)


def evidence_class(ln_b, high: float = math.log(100.0), low: float = math.log(0.01)) -> Column:
    """match, undecided or separate."""
    return F.when(_c(ln_b) >= high, "match").when(_c(ln_b) <= low, "separate").otherwise("undecided")


def posterior(ln_b, ln_prior_odds) -> Column:
    """Posterior probability from a Bayes factor and prior odds, both in logarithms."""
    return 1 / (1 + F.exp(-(_c(ln_b) + _c(ln_prior_odds))))


def with_posterior(match: DataFrame, ln_b: str, counts: list[float], sky_fraction: float = 1.0, rounds: int = 4, objects: float | None = None) -> DataFrame:
    """match with column posterior: prior N / product of full-sky counts, N set to the sum of posteriors round by round.

    One aggregate and one driver round trip a round; nothing but the sum comes back.
    """
    scaled = [n / sky_fraction for n in counts]
    n = objects / sky_fraction if objects else min(scaled)
    for k in range(rounds + 1):
        prior = n / math.prod(scaled)
        odds = math.log(prior) - math.log1p(-min(prior, 1 - 1e-12))
        column = posterior(ln_b, odds)
        if k == rounds or objects:
            break
        found = match.agg(F.sum(column)).first()[0] or 0.0
        n = max(min(found / sky_fraction, min(scaled)), 1e-9)
    return match.withColumn("posterior", column)


def ln_gaussian_property(value1, sigma1, value2, sigma2, spread: float) -> Column:
    """An extension: evidence in the difference of two measurements of one property, against two draws from a population.

    Under one source the difference has the errors' variance, under two also twice the population's (spread squared).
    """
    same = _c(sigma1) * _c(sigma1) + _c(sigma2) * _c(sigma2)
    apart = same + 2 * spread * spread
    gap = _c(value1) - _c(value2)
    return 0.5 * F.log(apart / same) - gap * gap / 2 * (1 / same - 1 / apart)
