"""Mixing sources to target weights by Pfair scheduling, with DataFrame functions only.

A source's documents stand in a pseudo-random order and are cut into blocks. With share w of a period of D slots, block j of a
source may start at slot floor(j D / w), its release, and must end by slot ceil((j + 1) D / w), its deadline. One block runs
in each slot: of the released ones, that with the earliest deadline (then the larger share, then the source's name). The
shares sum to D, so each source has had within less than one block of t w / D by every slot t, and the schedule
repeats with the period. A block's slot in the endless schedule is its place in the mix: every document is placed
once; when a source has ended, its slots are left out and the others keep their proportions.

Shares are whole slots of the period. Where weights are given the period has as many slots as the mix, up to MOST_PERIOD, so that rounding
moves no source by a block; past that, by at most slots / (2 period) blocks. The default weights use PERIOD slots, which the SQL repeats.
The schedule is simulated for one period in one row, STEP slots at a time: it holds the sources and a number for each slot, about
slots x sources steps, so it is for up to some thousands of sources. Ranks within a source come from counts of hash ranges, so a
source with a third of all rows is ranked by as many tasks as the others.

Edge cases: a source with a given weight of 0 or less, or with none, comes after all others end, sources by name; a null source is the source with the empty name; a null id is ranked before all ids; rows with equal ids are
ranked one after the other; an empty table gives an empty one; input columns named like an output are replaced.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Slots of a period (more if there are many sources), documents of a block, documents of a hash range.
PERIOD, BLOCK, RANGE = 1000, 16, 256
#: Slots of a period with given weights at most; slots that the simulation takes at a time.
MOST_PERIOD, STEP = 32_768, 128
#: Target weight of a source where none is given: its number of documents to this power.
TEMPERATURE = 0.5
PRIME = 2147483647
OUT = ["share", "period", "block", "slot", "release", "deadline", "mix_order"]


def scatter(column):
    """A portable pseudo-random number below PRIME from an integer id."""
    m = F.pmod(column, F.lit(PRIME)) * 1103515245 + 12345
    m = F.pmod(m, F.lit(PRIME))
    return F.pmod(F.pmod(m * m, F.lit(PRIME)) * 48271 + m * 69621 + 12345, F.lit(PRIME))


def shares(counts: DataFrame, weights: DataFrame | None = None, period: int = PERIOD, block: int = BLOCK) -> DataFrame:
    """(source, share, period, last) for counts (source, n): slots of a period, and those that the mix has; weights (source, weight) are optional.

    A share is the source's part of the period, rounded, 1 at least; the period is then the sum of the shares. A source that given
    weights leave out has share 0; if they leave out all, all are equal.
    """
    if weights is None:
        base = counts.withColumn("weight", F.pow(F.col("n").cast("double"), F.lit(TEMPERATURE)))
        least = F.lit(period)
    else:
        given = weights.groupBy(F.coalesce("source", F.lit("")).alias("source")).agg(F.max("weight").cast("double").alias("weight"))
        base = counts.join(given, "source", "left").withColumn("weight", F.greatest(F.coalesce("weight", F.lit(0.0)), F.lit(0.0)))
        base = base.join(F.broadcast(base.agg(F.max("weight").alias("most")))).withColumn("weight", F.when(F.col("most") > 0, F.col("weight")).otherwise(1.0)).drop("most")
        least = F.greatest(F.lit(period), F.least(F.lit(MOST_PERIOD), F.sum(F.ceil(F.col("n") / block))))
    whole = base.agg(F.sum("weight").alias("total"), F.greatest(least, 4 * F.count("*")).alias("slots"))
    share = F.greatest(F.lit(1), F.round(F.col("slots") * F.col("weight") / F.col("total"))).cast("long")
    part = base.join(F.broadcast(whole)).select("source", "n", F.when(F.col("weight") > 0, share).otherwise(0).alias("share"))
    part = part.join(F.broadcast(part.agg(F.sum("share").alias("period"))))
    turns = F.ceil(F.expr(f"try_divide(ceil(n / {block}), share)")) * F.col("period")
    return part.join(F.broadcast(part.agg(F.coalesce(F.max(turns), F.lit(0)).cast("long").alias("last")))).drop("n")


def schedule(shared: DataFrame) -> DataFrame:
    """(source, turn, place): the slot within the period of each turn of each source, by earliest deadline first.

    The whole state is one row: the sources by falling share, and the turns that each has had.
    """
    row = shared.filter("share > 0").agg(F.sort_array(F.collect_list(F.struct((-F.col("share")).alias("minus"), "source"))).alias("s"), F.max("period").alias("d"))
    nothing = F.array().cast("array<struct<i:int,turn:long>>")

    def step(state, t):
        share = lambda i: -F.element_at(F.col("s"), i + 1)["minus"]
        urgent = F.transform(
            state["had"],
            lambda k, i: F.when(F.floor(k * F.col("d") / share(i)) <= t, F.ceil((k + 1) * F.col("d") / share(i)) * F.size("s") + i),
        )
        pick = F.pmod(F.array_min(urgent), F.size("s")).cast("int")
        # The pick is an array of one, so that it is worked out once.
        return F.element_at(
            F.transform(
                F.array(pick),
                lambda p: F.struct(
                    F.transform(state["had"], lambda k, i: F.when(i == p, k + 1).otherwise(k)).alias("had"),
                    F.concat(state["out"], F.array(F.struct(p.alias("i"), F.element_at(state["had"], p + 1).alias("turn")))).alias("out"),
                ),
            ),
            1,
        )

    def some(state, t):  # STEP slots, whose picks join the others' once
        part = F.aggregate(F.sequence(t, F.least(t + (STEP - 1), F.col("d") - 1)), F.struct(state["had"].alias("had"), nothing.alias("out")), step)
        return F.element_at(F.transform(F.array(part), lambda x: F.struct(x["had"].alias("had"), F.concat(state["out"], x["out"]).alias("out"))), 1)

    start = F.struct(F.transform("s", lambda _: F.lit(0).cast("long")).alias("had"), nothing.alias("out"))
    run = row.filter("d > 0").select("s", F.aggregate(F.sequence(F.lit(0).cast("long"), F.col("d") - 1, F.lit(STEP).cast("long")), start, some, lambda state: state["out"]).alias("out"))
    return run.select("s", F.posexplode("out").alias("place", "x")).select(F.element_at("s", F.col("x.i") + 1)["source"].alias("source"), F.col("x.turn").alias("turn"), F.col("place").cast("long").alias("place"))


def mix(docs: DataFrame, weights: DataFrame | None = None, block: int = BLOCK, period: int = PERIOD) -> DataFrame:
    """docs with share, period, block, slot, release, deadline and mix_order; sorting by mix_order gives the mix.

    docs needs doc_id and source. weights: (source, weight); a source without one comes after the others.
    """
    key, spread = F.coalesce(F.col("source"), F.lit("")), scatter(F.coalesce(F.col("doc_id").cast("long"), F.lit(-1)))
    ranges = 1
    while ranges < 1 << 20 and ranges * RANGE < docs.count():
        ranges *= 2
    kept = [c for c in docs.columns if c.lower() not in OUT]
    rows = docs.select(*kept, key.alias("__source"), spread.alias("__spread")).withColumn("__range", F.floor(F.col("__spread") * ranges / PRIME).cast("int"))
    counts = rows.groupBy("__source", "__range").agg(F.count("*").alias("n"))
    shared = shares(counts.groupBy(F.col("__source").alias("source")).agg(F.sum("n").alias("n")), weights, period, block).withColumnRenamed("last", "__last")
    before = Window.partitionBy("__source").orderBy("__range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("__before", F.coalesce(F.sum("n").over(before), F.lit(0))).join(shared.withColumnRenamed("source", "__source"), "__source").drop("n")
    inside = Window.partitionBy("__source", "__range").orderBy("__spread", F.col("doc_id").asc_nulls_first())
    ranked = rows.withColumn("__rank", F.row_number().over(inside) - 1).join(offsets, ["__source", "__range"])
    ranked = ranked.withColumn("__rank", F.col("__rank") + F.col("__before")).withColumn("block", F.floor(F.col("__rank") / block).cast("long")).withColumn("__turn", F.expr("try_mod(block, share)"))
    turns = schedule(shared).select(F.col("source").alias("__s"), F.col("turn").alias("__t"), F.col("place").alias("__place"))
    if weights is not None:  # sources of share 0 have one place after all others, their blocks in order
        after = shared.filter("share = 0").select("source", F.lit(None).cast("long"), (F.row_number().over(Window.orderBy("source")) - 1).cast("long"))
        turns = turns.union(after)
    placed = ranked.join(turns, (F.col("__source") == F.col("__s")) & F.col("__turn").eqNullSafe(F.col("__t")))
    cycle = F.when(F.col("share") > 0, F.floor(F.expr("try_divide(block, share)")).cast("long") * F.col("period") + F.col("__place"))
    slot = F.coalesce(cycle, F.col("__last") + F.col("__place") * (1 << 40) + F.col("block"))
    return placed.select(
        *kept, "share", "period", "block", slot.alias("slot"),
        F.coalesce(F.floor(F.expr("try_divide(block * period, share)")).cast("long"), slot).alias("release"),
        F.coalesce(F.ceil(F.expr("try_divide((block + 1) * period, share)")).cast("long"), slot + 1).alias("deadline"),
        (slot * block + F.col("__rank") % block).alias("mix_order"),
    )


def mixed(docs: DataFrame, place: bool = False, **how) -> DataFrame:
    """docs' own columns in the order of the mix, range by range; with place, mix_order too, as files don't keep an order."""
    names = [c for c in docs.columns if not place or c.lower() != "mix_order"] + ["mix_order"] * place
    return mix(docs, **how).repartitionByRange("mix_order").sortWithinPartitions("mix_order").select(*names)


ORACLE = """
WITH RECURSIVE base AS (
  SELECT doc_id, source, coalesce(source, '') AS s, ((coalesce(doc_id, -1) % 2147483647 + 2147483647) % 2147483647 * 1103515245 + 12345) % 2147483647 AS m FROM documents
), spread AS (SELECT doc_id, source, s, (m * m % 2147483647 * 48271 + m * 69621 + 12345) % 2147483647 AS u FROM base),
counts AS (SELECT s, sqrt(count(*)) AS weight FROM spread GROUP BY s),
parts AS (SELECT s, greatest(1, round(greatest(1000, 4 * (SELECT count(*) FROM counts)) * weight / (SELECT sum(weight) FROM counts)))::BIGINT AS share FROM counts),
ordered AS (SELECT s, share, (sum(share) OVER ())::BIGINT AS d, row_number() OVER (ORDER BY share DESC, s) AS i FROM parts),
lists AS (SELECT list(share ORDER BY i) AS w, max(d) AS d, count(*) AS k FROM ordered),
run AS (
  SELECT -1::BIGINT AS t, (SELECT list_transform(w, lambda x: 0::BIGINT) FROM lists) AS had, 0::BIGINT AS pick
  UNION ALL
  SELECT t, list_transform(had, lambda x, j: CASE WHEN j = pick THEN x + 1 ELSE x END), pick FROM (
    SELECT r.t + 1 AS t, r.had, list_min(list_transform(r.had, lambda x, j: CASE WHEN (x * l.d) // l.w[j] <= r.t + 1
      THEN (((x + 1) * l.d + l.w[j] - 1) // l.w[j]) * l.k + j - 1 END)) % l.k + 1 AS pick
    FROM run r, lists l WHERE r.t + 1 < l.d)
), places AS (SELECT o.s, r.had[r.pick] - 1 AS turn, r.t AS place FROM run r JOIN ordered o ON o.i = r.pick WHERE r.t >= 0),
ranked AS (
  SELECT p.*, o.share, o.d, row_number() OVER (PARTITION BY p.s ORDER BY u, doc_id NULLS FIRST) - 1 AS r FROM spread p JOIN ordered o USING (s)
), placed AS (
  SELECT k.*, k.r // 16 AS block, (k.r // 16) // share * d + place AS slot FROM ranked k JOIN places x ON x.s = k.s AND x.turn = (k.r // 16) % share
)
SELECT doc_id, source, share, d AS period, block, slot, block * d // share AS release, ((block + 1) * d + share - 1) // share AS deadline, slot * 16 + r % 16 AS mix_order FROM placed
"""
