"""One-permutation MinHash fingerprints with optimal densification and packed low-order bits, in DataFrame functions only.

Each shingle is hashed once: its high bits choose a bin, the least hash of a bin wins. An empty bin takes the value of the
first full bin on its own pseudo-random walk over all bins. The walks are fixed and independent of the document, and each is a
permutation, so it ends. The fingerprint stores the low 8 bits of each bin. Two unequal values agree by chance once in 256
times; likeness takes that out: (agreement - 1/256) / (1 - 1/256), not below 0.

Sets are of the runs of 5 words of the lower-cased text (words apart by space and 9-13); a text with fewer words has its whole
sequence as one. A text without words has the fingerprint "-": like only to another of these.

Edge cases: a null text is empty; a null id ranks below all ids; rows with the same id are one document for their neighbour's
edit (its least head of text), and each has a row of its own; the only document's next one is itself.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpointed, id_of

BIN_BITS, BITS, WIDTH = 7, 8, 5
BINS = 1 << BIN_BITS
#: Steps of the walks taken by all bins at once; bins that are still empty then look along their whole walk.
ROUNDS = 6
EMPTY = "-"
#: Ids of a range in which neighbours are found, and the most coarse ranges.
RANGE, COARSE = 256, 1024


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value worked out once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def walks() -> list[list[int]]:
    """For each bin, all bins in the order in which it asks them: an odd step from an offset, both scrambled from its number."""
    out = []
    for i in range(BINS):
        x = (i + 1) * 0x9E3779B1 & 0xFFFFFFFF
        x = (x ^ x >> 15) * 0x85EBCA77 & 0xFFFFFFFF
        x = (x ^ x >> 13) * 0xC2B2AE3D & 0xFFFFFFFF
        x ^= x >> 16
        offset, step = x % BINS, (x >> 8) % (BINS // 2) * 2 + 1
        out.append([(offset + step * a) % BINS for a in range(BINS)])
    return out


def _literal(values: list[int], kind: str = "int") -> Column:
    """A constant array: one literal to parse and fold, however long."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast(f"array<{kind}>")


def shingle_hashes(text: Column) -> Column:
    trimmed = F.btrim(F.lower(text), F.lit(" \t\n\x0b\x0c\r"))

    def runs(w: Column) -> Column:
        each = F.transform(F.sequence(F.lit(1), F.size(w) - WIDTH + 1), lambda i: F.xxhash64(*[F.element_at(w, i + j) for j in range(WIDTH)]))
        return F.when(F.size(w) >= WIDTH, each).otherwise(F.array(F.xxhash64(w)))

    return F.when(trimmed == "", F.array().cast("array<bigint>")).otherwise(let(F.split(trimmed, r"[\x20\x09-\x0D]+"), runs))


def bins(hashes: Column) -> Column:
    """The least hash of each bin, null where it has none. A marker, the largest hash of each bin, stands in every bin."""
    shift = 64 - BIN_BITS
    markers = [((i - BINS // 2) << shift) + (1 << shift) - 1 for i in range(BINS)]
    least = let(
        F.sort_array(F.concat(hashes, _literal(markers, "bigint"))),
        lambda a: F.filter(a, lambda x, i: (i == 0) | (F.shiftright(x, shift) != F.shiftright(F.get(a, i - 1), shift))),
    )
    return F.transform(least, lambda x: F.when(x.bitwiseAND(F.lit((1 << shift) - 1)) != (1 << shift) - 1, x))


def dense(least: Column) -> Column:
    """bins() with each empty bin filled from the first full bin of its walk."""
    steps = walks()

    def fill(v: Column) -> Column:
        def rounds(now: Column, a: int) -> Column:
            if a == ROUNDS:
                last = _literal([k for w in steps for k in w])
                rest = F.transform(now, lambda x, i: F.coalesce(x, F.get(F.filter(F.transform(F.slice(last, i * BINS + 1, BINS), lambda k: F.get(v, k)), lambda y: y.isNotNull()), 0)))
                return F.when(F.exists(now, lambda x: x.isNull()), rest).otherwise(now)
            step = _literal([w[a] for w in steps])
            return let(F.transform(now, lambda x, i: F.coalesce(x, F.get(v, F.get(step, i)))), lambda following: rounds(following, a + 1))

        return F.when(F.exists(v, lambda x: x.isNull()), rounds(v, 0)).otherwise(v)

    return let(least, fill)


def fingerprint(text: Column) -> Column:
    """The packed low bits as lower-case hex, two digits a bin."""

    def packed(h: Column) -> Column:
        digits = F.transform(dense(bins(h)), lambda x: F.lpad(F.hex(x.bitwiseAND(F.lit((1 << BITS) - 1))), 2, "0"))
        return F.when(F.size(h) == 0, F.lit(EMPTY)).otherwise(F.lower(F.array_join(digits, "")))

    return let(shingle_hashes(text), packed)


def likeness(a: Column, b: Column) -> Column:
    """Estimated Jaccard similarity of two fingerprints, 0 to 1."""
    same = F.aggregate(F.sequence(F.lit(0), F.lit(BINS - 1)), F.lit(0), lambda n, i: n + F.when(F.substring(a, i * 2 + 1, F.lit(2)) == F.substring(b, i * 2 + 1, F.lit(2)), 1).otherwise(0))
    chance = 1.0 / (1 << BITS)
    return F.when(a == b, F.lit(1.0)).when((a == EMPTY) | (b == EMPTY), F.lit(0.0)).otherwise(F.greatest(F.lit(0.0), (same / BINS - chance) / (1 - chance)))


def _search(value: Column, edges: list[int]) -> Column:
    """How many of the sorted edges, after the first, are not above the value."""
    size = 1
    while size < len(edges):
        size *= 2
    table, powers = _literal([*edges, *([2**63 - 1] * (2 * size - len(edges)))], "bigint"), []
    while size:
        powers.append(size)
        size //= 2
    return F.aggregate(_literal(powers), F.lit(0), lambda at, step: at + F.when(value >= F.get(table, at + step), step).otherwise(0))


def next_lower(ids: DataFrame) -> DataFrame:
    """(id, next_id) for distinct ids: the next one in descending order, after the last the first. No global sort.

    Coarse ranges from approximate quantiles, at most COARSE, are cut evenly; neighbours meet inside a cut, cuts meet through
    their largest ids. No join is needed.
    """
    n, low, high = ids.agg(F.count("*"), F.min("id"), F.max("id")).first()
    if not n:
        return ids.select("id", F.col("id").alias("next_id"))
    coarse = min(COARSE, max(1, n // (16 * RANGE)))
    edges = [low, *(sorted(set(ids.agg(F.percentile_approx("id", [i / coarse for i in range(1, coarse)], 10_000)).first()[0])) if coarse > 1 else [])]
    edges = sorted(set(edges))
    fine = max(1, -(-n // (len(edges) * RANGE)))
    rows = ids.withColumn("c", _search(F.col("id"), edges))
    start, end = (F.get(_literal([*edges, high + 1][k:], "bigint"), F.col("c")) for k in (0, 1))
    part = F.least(F.lit(fine - 1), F.floor((F.col("id").cast("double") - start.cast("double")) * fine / F.greatest(F.lit(1.0), end.cast("double") - start.cast("double")))).cast("int")
    rows = checkpointed(rows.withColumn("f", part))  # ids alone
    cuts = rows.groupBy("c", "f").agg(F.max("id").alias("id"))
    tops = cuts.groupBy("c").agg(F.max("id").alias("id"))
    # The largest id below a range stands in it as a guest, after its own ids; below the last range, the first id.
    guests = tops.select("c", F.lit(-1).alias("f"), F.coalesce(F.lead("id").over(Window.orderBy(F.desc("c"))), F.lit(high)).alias("id"))
    cuts = cuts.unionByName(guests).withColumn("id", F.lead("id").over(Window.partitionBy("c").orderBy(F.desc("f")))).filter("f >= 0")
    both = rows.withColumn("guest", F.lit(False)).unionByName(cuts.withColumn("guest", F.lit(True)))
    lead = F.lead("id").over(Window.partitionBy("c", "f").orderBy("guest", F.desc("id")))
    return both.withColumn("next_id", lead).filter("NOT guest").select("id", "next_id")


def edited_fingerprints(docs: DataFrame) -> DataFrame:
    """Fingerprints of each text of docs (doc_id, text) and of its edited text, with their likeness and that of the next document.

    The edited text has the last half of the code points, rounded down, replaced by the first as many of the next document in
    descending id order.
    """
    base = docs.select(id_of().alias("id"), F.coalesce("text", F.lit("")).alias("text"))
    known = checkpointed(base.select("id", F.xxhash64("text").alias("mark"), F.char_length("text").cast("long").alias("n_chars"), fingerprint(F.col("text")).alias("fingerprint")))
    heads = known.groupBy("id").agg(F.max("n_chars").alias("n"), F.min("fingerprint").alias("f"))
    pairs = checkpointed(next_lower(heads.select("id")))
    asked = pairs.join(heads.select("id", "n"), "id").select(F.col("next_id").alias("id"), F.col("id").alias("target"), F.floor(F.col("n") / 2).cast("int").alias("take"))
    given = base.join(asked, "id").select("target", F.substring(F.col("text"), F.lit(1), F.col("take")).alias("head")).groupBy("target").agg(F.min("head").alias("head"))
    n = F.char_length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.col("head"), F.lit(1), half))
    main = base.join(given, F.col("id") == F.col("target")).select("id", F.xxhash64("text").alias("mark"), edited.alias("edited"))
    main = main.select("id", "mark", F.sha2("edited", 256).alias("edited_sha256"), fingerprint(F.col("edited")).alias("edited_fingerprint"))
    own = known.groupBy("id", F.col("mark").alias("own_mark")).agg(F.max("n_chars").alias("n_chars"), F.max("fingerprint").alias("fingerprint"))
    following = pairs.join(heads.select(F.col("id").alias("next_id"), F.col("f").alias("next_fingerprint")), "next_id")
    # All by id, as the texts already lie: only the narrow sides move.
    out = main.join(own, "id").filter("mark = own_mark").join(following, "id")
    return out.select(
        F.expr(f"CASE WHEN id > {-(2**63) + 1} THEN id END").alias("doc_id"), "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint",
        likeness(F.col("fingerprint"), F.col("edited_fingerprint")).alias("near_edited"), likeness(F.col("fingerprint"), F.col("next_fingerprint")).alias("near_next"),
    )
