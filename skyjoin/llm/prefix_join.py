"""Exact n-gram Jaccard self-join and its classes, with prefix trees over globally ordered sets.

The global order of shingles runs from rare to frequent: by a counter of a fixed-size sketch of the whole corpus, then by
hash. Any two sets of Jaccard similarity t or more share one of the first n - ceil(t n) + 1 shingles of each.

1. One scan gives each document its set size and a digest of its set, and each task's sketch counters.
2. One scan sends each set's prefix to buckets of shingles, packed. A task sends equal sets once. A shingle that more than SMALL
   documents of a packet hold is combined there: each class of sizes sends its least document, the others are tied to that one.
3. In a bucket, shingles of up to SMALL documents give pairs with the number of prefix shingles they share; pairs whose total
   can't reach the needed overlap go. A more frequent shingle gives one star a class of sizes, and ties between neighbouring
   classes: sizes within t never lie farther apart. So no group is expanded into pairs, and what a shingle sends grows with the packets
   alone. Pairs that share a frequent shingle are tied by it; all others have a full count.
4. Components of these candidates are blocks: no link crosses two blocks. One scan sends the sets of block members (found by a
   bitmap of bounded size) to their blocks, each set once.
5. A block's sets stand in a prefix tree, common shingles first so that sets share long paths. Each set walks the tree
   level by level with the overlap shared on a path, leaving subtrees whose remaining lengths can't reach the threshold.
   Sets that are already connected aren't asked for again.
6. A block of more than CHUNK documents or CUT_BYTES of sets is cut by both. A few of its documents stand in every cut, so that a group
   of near copies is connected by its cuts alone. What is outside the block's largest class then meets all cuts of the block: sets are
   copied once for each cut of that rest, not of the block. A block of many classes still costs the square of its cuts.

Broadcasts: the sketch (at most 2**24 counters of 2 bytes) and the bitmap (at most 2**26 bits), whatever the input.

Edge cases: null or blank texts have an empty set, link with nothing and are their own class; rows with the same id are one
document; a null id gives a null class and no links; extra columns are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, chunks, power_of_two, released, returning, text_bytes
from .components import components
from .shingles import WIDTH, shingle_sets

PERCENT = 75
#: Documents of a shingle up to which pairs are made; of a block's cut; postings of a bucket; digests that a task keeps.
SMALL, CHUNK, BUCKET, SEEN = 16, 512, 200_000, 200_000
#: Bytes of a cut's sets; documents of a block that stand in all its cuts; exponents of the sketch's parts and of the bitmap.
CUT_BYTES, PIVOTS, SKETCH_PART, MEMBER_BITS = 4 << 20, 4, 16, (20, 26)


def least_overlap(a, b, percent: int = PERCENT):
    """The least integer o with 100 o >= percent (a + b - o)."""
    return -(-percent * (a + b) // (100 + percent))


def size_class(n: np.ndarray, percent: int = PERCENT) -> np.ndarray:
    """Numbers of classes of sizes: two sizes that the threshold allows together are in one class or in neighbouring ones."""
    return np.floor(np.log(n) / (np.log(100 / min(percent, 99.9)) * (1 + 1e-9))).astype(np.int64)


def prefix_length(n: int, percent: int = PERCENT) -> int:
    return n - -(-percent * n // 100) + 1 if n else 0


class _Fresh:
    """Whether a digest is new to this task; forgets all when full, which only repeats work."""

    def __init__(self):
        self.seen: set[bytes] = set()

    def __call__(self, digest: bytes) -> bool:
        if digest in self.seen:
            return False
        if len(self.seen) >= SEEN:
            self.seen.clear()
        self.seen.add(digest)
        return True


def _digest(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


_SCAN = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("digest", pa.binary()), ("block", pa.int32()), ("part", pa.int32()), ("counts", pa.binary())])


def _scan(width: int, bits: int):
    """Step 1. Rows of documents have no block; rows of counters have no n."""

    def run(batches):
        counts, fresh = np.zeros(1 << bits, np.uint32), _Fresh()
        waiting: list[np.ndarray] = []
        for batch in batches:
            for part in chunks(batch, 1):
                sizes, digests = [], []
                for s in shingle_sets(text_bytes(part.column(1)), width):
                    sizes.append(len(s))
                    digests.append(d := _digest(s) if len(s) else None)
                    if d and fresh(d):
                        waiting.append(s)
                if sum(map(len, waiting)) > 1 << 20:
                    np.add.at(counts, (np.concatenate(waiting) >> np.uint64(64 - bits)).astype(np.int64), 1)
                    waiting = []
                none = pa.nulls(len(sizes))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), none.cast(pa.int32()), none.cast(pa.int32()), none.cast(pa.binary())], schema=_SCAN)
        if waiting:
            np.add.at(counts, (np.concatenate(waiting) >> np.uint64(64 - bits)).astype(np.int64), 1)
        if counts.any():
            blocks = counts.reshape(-1, 1 << min(bits, SKETCH_PART))
            none = pa.nulls(len(blocks))
            packed = [zlib.compress(x.tobytes(), 1) for x in blocks]
            yield pa.RecordBatch.from_arrays([none.cast(pa.int64()), none.cast(pa.int64()), none.cast(pa.binary()), pa.array(range(len(blocks)), pa.int32()), pa.array([TaskContext.get().partitionId() // 32] * len(blocks), pa.int32()), pa.array(packed, pa.binary())], schema=_SCAN)

    return run


def _add(rows: pd.DataFrame) -> pd.DataFrame:
    total = sum(np.frombuffer(zlib.decompress(x), np.uint32).astype(np.uint64) for x in rows["counts"])
    packed = zlib.compress(np.minimum(total, 2**32 - 1).astype(np.uint32).tobytes(), 1)
    return pd.DataFrame({"block": rows["block"].iloc[:1], "part": rows["part"].iloc[:1], "counts": [packed]})


def _sketch(scanned: DataFrame, bits: int) -> bytes:
    """The corpus's counters as 16-bit numbers, scaled down if the largest needs it."""
    schema = "block int, part int, counts binary"
    rows = scanned.filter("block IS NOT NULL").select("block", "part", "counts").groupBy("block", "part").applyInPandas(_add, schema)
    out = np.zeros(1 << bits, np.uint32)
    size = 1 << min(bits, SKETCH_PART)
    for row in rows.groupBy("block").applyInPandas(_add, schema).collect():  # 2**(bits - SKETCH_PART) rows
        out[row.block * size : (row.block + 1) * size] = np.frombuffer(zlib.decompress(row.counts), np.uint32)
    # Counters near the mean keep single steps; far above it only the order of magnitude matters.
    low = np.minimum(out, 32768).astype(np.uint32)
    return (low + (np.log2(np.maximum(out, 32768) / 32768) * 1900).astype(np.uint32)).astype(np.uint16).tobytes()


def ordered(s: np.ndarray, counts: np.ndarray, most: int | None = None) -> np.ndarray:
    """The first `most` shingles of a sorted set in the global order."""
    bits = np.uint64(64 - int(len(counts)).bit_length() + 1)
    key = counts[(s >> bits).astype(np.int64)].astype(np.uint64) << np.uint64(48) | s >> np.uint64(16)
    if most is not None and most < len(s):
        at = np.argpartition(key, most)[: most + 1]
        # A tie at the cut is decided by hash, as everywhere.
        at = at[np.lexsort((s[at], key[at]))][:most] if (key[at] == key[at].max()).sum() == 1 else np.lexsort((s, key))[:most]
    else:
        at = np.lexsort((s, key))
    return s[at]


def stars(token: np.ndarray, doc: np.ndarray, n: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ties (documents, their centres) of frequent shingles, and the places of the centres: the least document of each class of sizes."""
    kind = size_class(n, percent)
    at = np.lexsort((doc, kind, token))
    new = np.append(True, (token[at][1:] != token[at][:-1]) | (kind[at][1:] != kind[at][:-1])) if len(at) else np.zeros(0, bool)
    centre = at[np.flatnonzero(new)][np.cumsum(new) - 1] if len(at) else at
    return doc[at], doc[centre], at[new]


def _distinct(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs of different numbers, the smaller one first."""
    low, high = np.minimum(a, b), np.maximum(a, b)
    at = np.lexsort((high, low))
    low, high = low[at], high[at]
    keep = (low != high) & np.append(True, (low[1:] != low[:-1]) | (high[1:] != high[:-1])) if len(low) else np.zeros(0, bool)
    return low[keep], high[keep]


def _postings(width: int, percent: int, sketch, buckets: int):
    """Step 2: rows of (bucket, packed postings, packed ties). Sizes below 0 mark the centres of shingles that are frequent in the packet."""

    def run(batches):
        counts, fresh = np.frombuffer(sketch.value, np.uint16), _Fresh()
        held: list[tuple[np.ndarray, int, int]] = []
        size = 0

        def flush():
            token = np.concatenate([x for x, _, _ in held])
            lengths = [len(x) for x, _, _ in held]
            doc = np.repeat(np.array([d for _, d, _ in held], np.int64), lengths)
            n = np.repeat(np.array([k for _, _, k in held], np.int32), lengths)
            _, back, often = np.unique(token, return_inverse=True, return_counts=True)
            hot = np.flatnonzero(often[back] > SMALL)
            member, centre, at = stars(token[hot], doc[hot], n[hot], percent)
            ties = _distinct(member, centre)
            rest, first = np.flatnonzero(often[back] <= SMALL), hot[at]
            token, doc, n = (np.concatenate((x[rest], y)) for x, y in ((token, token[first]), (doc, doc[first]), (n, -n[first])))
            bucket = ((token >> np.uint64(7)) % np.uint64(buckets)).astype(np.int32)
            at = np.argsort(bucket, kind="stable")
            token, doc, n, bucket = token[at], doc[at], n[at], bucket[at]
            starts = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))
            ends = np.append(starts[1:], len(bucket))
            blobs = [token[a:b].tobytes() + doc[a:b].tobytes() + n[a:b].tobytes() for a, b in zip(starts, ends, strict=True)]
            packed = [np.stack(ties).tobytes()] + [b""] * (len(starts) - 1)
            return pa.RecordBatch.from_arrays([pa.array(bucket[starts], pa.int32()), pa.array(blobs, pa.binary()), pa.array(packed, pa.binary())], ["bucket", "blob", "ties"])

        for batch in batches:
            for part in chunks(batch, 1):
                for doc, s in zip(part.column(0).to_pylist(), shingle_sets(text_bytes(part.column(1)), width), strict=True):
                    if len(s) and fresh(_digest(s)):
                        held.append((ordered(s, counts, prefix_length(len(s), percent)), doc, len(s)))
                        size += len(held[-1][0])
                if size > 1 << 20:
                    yield flush()
                    held, size = [], 0
        if held:
            yield flush()

    return run


_PAIRS = "a long, b long, na long, nb long, shared long"


def _candidates(percent: int):
    """Step 3: rows of (a, b, sizes, shared prefix shingles) from one bucket; shared is null for a tie."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        tokens, docs, sizes = [], [], []
        for blob in rows["blob"]:
            k = len(blob) // 20
            tokens.append(np.frombuffer(blob, np.uint64, k))
            docs.append(np.frombuffer(blob, np.int64, k, 8 * k))
            sizes.append(np.frombuffer(blob, np.int32, k, 16 * k))
        token, doc, n = np.concatenate(tokens), np.concatenate(docs), np.concatenate(sizes).astype(np.int64)
        frequent, n = n < 0, np.abs(n)
        at = np.lexsort((doc, n, token))
        token, doc, n, frequent = token[at], doc[at], n[at], frequent[at]
        starts = np.flatnonzero(np.append(True, token[1:] != token[:-1]))
        count = np.diff(np.append(starts, len(token)))
        hot = (count > SMALL) | (np.add.reduceat(frequent, starts) > 0)
        found = []
        for k in np.unique(count[(count > 1) & ~hot]):
            i, j = np.triu_indices(k, 1)
            base = starts[(count == k) & ~hot][:, None]
            x, y = (base + i).ravel(), (base + j).ravel()
            ok = (100 * n[x] >= percent * n[y]) & (doc[x] != doc[y])  # n[x] <= n[y]
            found.append((x[ok], y[ok]))
        pairs = pd.DataFrame({"a": [], "b": [], "na": [], "nb": [], "shared": []}, dtype="int64")
        if found:
            x, y = np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
            flip = doc[x] > doc[y]
            x, y = np.where(flip, y, x), np.where(flip, x, y)
            order = np.lexsort((doc[y], doc[x]))
            x, y = x[order], y[order]
            if len(x):
                first = np.flatnonzero(np.append(True, (doc[x][1:] != doc[x][:-1]) | (doc[y][1:] != doc[y][:-1])))
                pairs = pd.DataFrame({"a": doc[x[first]], "b": doc[y[first]], "na": n[x[first]], "nb": n[y[first]], "shared": np.diff(np.append(first, len(x)))})
        ties = [np.frombuffer(x, np.int64).reshape(2, -1) for x in rows["ties"] if x]
        own = np.flatnonzero(np.repeat(hot, count))
        if len(own):
            member, centre, at = stars(token[own], doc[own], n[own], percent)
            ties.append(np.stack((member, centre)))
            heads = own[at]  # by shingle, then class: neighbouring classes are tied by their centres
            kind = size_class(n[heads], percent)
            near = np.flatnonzero((token[heads][1:] == token[heads][:-1]) & (kind[1:] - kind[:-1] == 1))
            ties.append(np.stack((doc[heads[near]], doc[heads[near + 1]])))
        out = pairs.astype({"shared": "Int64"})
        if ties:
            a, b = _distinct(*np.concatenate(ties, axis=1))
            extra = pd.DataFrame({"a": a, "b": b, "na": 0, "nb": 0, "shared": pd.array([None] * len(a), "Int64")})
            out = pd.concat([out, extra]) if len(out) and len(extra) else extra if len(extra) else out
        return out

    return run


def _members(width: int, bitmap):
    """Step 4: (doc_id, n, packed sorted set) of the documents whose slot is in the bitmap."""

    def run(batches):
        flat = np.frombuffer(bitmap.value, np.uint64)
        for batch in batches:
            slot = batch.column(2).to_numpy(zero_copy_only=False).astype(np.int64)
            here = np.flatnonzero(flat[slot >> 6] >> (slot & 63).astype(np.uint64) & np.uint64(1))
            own = batch.take(pa.array(here))
            for part in chunks(own, 1) if own.num_rows else ():
                sets = list(shingle_sets(text_bytes(part.column(1)), width))
                keep = [i for i, s in enumerate(sets) if len(s)]
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(keep, pa.int64())), pa.array([sets[i].tobytes() for i in keep], pa.binary())], ["doc_id", "shingles"])

    return run


class PrefixTree:
    """Sets of integers, sorted, in a path-compressed prefix tree kept in arrays by level."""

    def __init__(self, sets: list[np.ndarray]):
        """sets: ascending arrays of int32, in lexicographic order."""
        self.size = np.array([len(s) for s in sets], np.int64)
        parent, begin, end, source = [-1], [0], [0], [0]
        stack, leaf = [0], []
        for k, s in enumerate(sets):
            same = 0
            if k:
                m = min(len(s), len(sets[k - 1]))
                differ = np.flatnonzero(s[:m] != sets[k - 1][:m])
                same = int(differ[0]) if len(differ) else m
            last = -1
            while end[stack[-1]] > same:
                last = stack.pop()
            if end[stack[-1]] < same:  # the path of the previous set forks inside a node
                parent.append(stack[-1])
                begin.append(end[stack[-1]])
                end.append(same)
                source.append(source[last])
                stack.append(len(parent) - 1)
                parent[last], begin[last] = stack[-1], same
            if len(s) > same or not k:
                parent.append(stack[-1])
                begin.append(same)
                end.append(len(s))
                source.append(k)
                stack.append(len(parent) - 1)
            leaf.append(stack[-1])
        self.leaf, self.parent, self.end = np.array(leaf), np.array(parent), np.array(end, np.int64)
        level = np.zeros(len(parent), np.int64)
        for i in np.argsort(self.end, kind="stable"):
            if i:
                level[i] = level[self.parent[i]] + 1
        self.levels = [np.flatnonzero(level == k) for k in range(1, int(level.max()) + 1)]
        self.low, self.high = np.full(len(parent), 2**62, np.int64), np.zeros(len(parent), np.int64)
        np.minimum.at(self.low, self.leaf, self.size)
        np.maximum.at(self.high, self.leaf, self.size)
        for nodes in reversed(self.levels):
            np.minimum.at(self.low, self.parent[nodes], self.low[nodes])
            np.maximum.at(self.high, self.parent[nodes], self.high[nodes])
        parts = [sets[k][a:b] for k, a, b in zip(source, begin, end, strict=True)]
        self.items = np.concatenate(parts) if parts else np.zeros(0, np.int32)
        self.stop = np.cumsum([len(p) for p in parts])
        self.start = self.stop - [len(p) for p in parts]
        self.last = np.array([p[-1] if len(p) else -1 for p in parts])

    def linked(self, probe: np.ndarray, values: int, percent: int = PERCENT) -> np.ndarray:
        """Numbers of the sets whose similarity to the probe reaches the threshold."""
        inside = np.zeros(values, bool)
        inside[probe] = True
        total = np.concatenate(([0], np.cumsum(inside[self.items])))
        own, n = total[self.stop] - total[self.start], len(probe)
        partial, alive = np.zeros(len(own), np.int64), np.zeros(len(own), bool)
        alive[0] = True
        for nodes in self.levels:
            nodes = nodes[alive[self.parent[nodes]]]
            if not len(nodes):
                break
            shared = partial[self.parent[nodes]] + own[nodes]
            left = np.minimum(n - np.searchsorted(probe, self.last[nodes], "right"), self.high[nodes] - self.end[nodes])
            low = np.maximum(self.low[nodes], -(-percent * n // 100))
            ok = (shared + left >= least_overlap(n, low, percent)) & (low <= self.high[nodes]) & (percent * self.low[nodes] <= 100 * n)
            partial[nodes], alive[nodes] = shared, ok
        at = np.flatnonzero(alive[self.leaf])
        shared = partial[self.leaf[at]]
        return at[100 * shared >= percent * (n + self.size[at] - shared)]


def linked_classes(sets: list[np.ndarray], percent: int = PERCENT, quiet: np.ndarray | None = None) -> np.ndarray:
    """A class number for each non-empty set: sets are in one class if a chain of links joins them. Quiet sets are in one class from the start."""
    values, code, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    rank = np.empty(len(values), np.int32)
    rank[np.lexsort((values, -count))] = np.arange(len(values), dtype=np.int32)
    flat, bounds = rank[code], np.cumsum([0, *(len(s) for s in sets)])
    coded = [np.sort(flat[a:b]) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
    order = sorted(range(len(sets)), key=lambda i: coded[i].astype(">u4").tobytes())
    tree = PrefixTree([coded[i] for i in order])
    label = np.arange(len(order))
    still = quiet[order] if quiet is not None else np.zeros(len(order), bool)
    if still.any():
        label[still] = label[np.argmax(still)]
    for k, i in enumerate(order):
        if (label == label[k]).all():
            break
        if still[k]:
            continue
        hit = tree.linked(coded[i], len(values), percent)
        old = np.unique(label[hit])
        label[np.isin(label, old)] = old[0] if len(old) else label[k]
    out = np.empty(len(order), np.int64)
    out[order] = label
    return out


def _join(percent: int):
    """Step 5: (doc_id, label) from one block or from what meets in one task of a cut block; rows that are `still` are in one class already."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        ids = rows["doc_id"].to_numpy()
        label = linked_classes([np.frombuffer(x, np.uint64) for x in rows["shingles"]], percent, rows["still"].to_numpy(bool))
        least = pd.Series(ids).groupby(label).transform("min")
        return pd.DataFrame({"doc_id": ids, "label": least.to_numpy()})

    return run


def _meet(percent: int):
    """Step 6, first: the classes inside one cut, and which of the block's pivots are in each (a bit for each pivot)."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        ids, pivot = rows["doc_id"].to_numpy(), rows["pivot"].to_numpy()
        label = linked_classes([np.frombuffer(x, np.uint64) for x in rows["shingles"]], percent)
        least = pd.Series(ids).groupby(label).transform("min")
        mask = pd.Series(np.where(pivot >= 0, 1 << np.maximum(pivot, 0), 0)).groupby(label).transform(lambda x: np.bitwise_or.reduce(x.to_numpy()))
        out = pd.DataFrame({"doc_id": ids, "class": least.to_numpy(), "label": rows["label"].to_numpy(), "mask": mask.to_numpy(), "guest": rows["guest"].to_numpy()})
        return out.assign(shingles=rows["shingles"].where(~rows["guest"], None).to_numpy())

    return run


def _planned(blocks: DataFrame, sizes: DataFrame) -> DataFrame:
    """blocks (node, label) as (doc_id, label, cuts, pivot) by sizes (doc_id, n): what becomes of a document is settled before its set is sent."""
    members = blocks.withColumnRenamed("node", "doc_id").join(sizes.groupBy("doc_id").agg(F.max("n").alias("n")), "doc_id")
    cuts = F.ceil(F.greatest(F.count("*") / CHUNK, F.sum(8 * F.col("n")) / CUT_BYTES)).cast("int")
    members = members.join(members.groupBy("label").agg(cuts.alias("cuts")), "label").select("doc_id", "label", "cuts")
    picked = members.filter("cuts > 1").groupBy("label", F.expr(f"cast(pmod(xxhash64(doc_id, 5), {PIVOTS}) AS int)").alias("p")).agg(F.min(F.struct(F.xxhash64("doc_id", F.lit(11)), "doc_id"))["doc_id"].alias("doc_id"))
    return members.join(picked.select("doc_id", "p"), "doc_id", "left").select("doc_id", "label", "cuts", F.coalesce("p", F.lit(-1)).alias("pivot"))


def _cut_blocks(big: DataFrame, percent: int) -> DataFrame:
    """Step 6 over big (doc_id, label, shingles, cuts, pivot): edges (a, b) that connect the classes of cut blocks."""
    marked = big.withColumns({"cut": F.expr("cast(pmod(xxhash64(doc_id, 3), cuts) AS int)"), "guest": F.lit(False)})
    guests = marked.filter("pivot >= 0").withColumns({"cut": F.explode(F.expr("filter(sequence(0, cuts - 1), x -> x <> cut)")), "guest": F.lit(True)})
    schema = "doc_id long, class long, label long, mask long, guest boolean, shingles binary"
    inside = checkpointed(marked.unionByName(guests).groupBy("label", "cut").applyInPandas(_meet(percent), schema))
    first = inside.filter("doc_id <> class").select(F.col("doc_id").alias("a"), F.col("class").alias("b"))
    # The pivot whose class is the largest over all cuts: what holds it is connected.
    own = inside.filter("NOT guest").withColumn("size", F.octet_length("shingles"))
    has = [F.expr(f"shiftright(mask, {j}) & 1") for j in range(PIVOTS)]
    best = F.array_max(F.array(*[F.struct(F.sum(h).alias("n"), F.lit(j).alias("j"), F.sum(h * F.col("size")).alias("bytes")) for j, h in enumerate(has)]))
    counts = own.groupBy("label").agg(F.count("*").alias("n"), F.sum("size").alias("bytes"), best.alias("best"))
    cuts = lambda n, size: F.ceil(F.greatest(n / CHUNK, size / CUT_BYTES)).cast("int")
    main = counts.select("label", "best.j", cuts(F.col("best.n"), F.col("best.bytes")).alias("m"), cuts(F.col("n") - F.col("best.n"), F.col("bytes") - F.col("best.bytes")).alias("r")).filter("r > 0")
    owned = own.join(main, "label").withColumn("still", F.expr("shiftright(mask, j) & 1 = 1"))
    owned = owned.withColumn("own", F.expr("cast(pmod(xxhash64(doc_id, 7), IF(still, m, r)) AS int)"))
    # The rest's cut i meets the connected ones' cut j as (i, j, true), the rest's cut k as (min, max, false).
    meets = """IF(still, transform(sequence(0, r - 1), i -> named_struct('i', i, 'j', own, 'side', true)),
      concat(IF(m > 0, transform(sequence(0, m - 1), j -> named_struct('i', own, 'j', j, 'side', true)), array()), transform(sequence(0, r - 1), k -> named_struct('i', least(own, k), 'j', greatest(own, k), 'side', false))))"""
    tasks = owned.select("doc_id", "label", "shingles", "still", F.explode(F.expr(meets)).alias("t")).select("doc_id", "label", "shingles", "still", "t.*")
    across = tasks.groupBy("label", "i", "j", "side").applyInPandas(_join(percent), "doc_id long, label long")
    return first.unionByName(across.filter("doc_id <> label").select(F.col("doc_id").alias("a"), F.col("label").alias("b")))


def scanned(docs: DataFrame, width: int = WIDTH) -> tuple[DataFrame, int]:
    """Step 1 over docs (doc_id, text), checkpointed, and the sketch's bits."""
    bits = power_of_two(16 * docs.count(), 16, 24)
    return checkpointed(docs.mapInArrow(returning(_scan(width, bits)), "doc_id long, n long, digest binary, block int, part int, counts binary")), bits


def link_classes(docs: DataFrame, percent: int = PERCENT, width: int = WIDTH) -> DataFrame:
    """doc_id, n_shingles and component_id of each row of docs (doc_id, text): the join and its classes."""
    spark = docs.sparkSession
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    first, bits = scanned(docs, width)
    sketch = spark.sparkContext.broadcast(_sketch(first, bits))
    released()
    rows = first.filter("block IS NULL").select("doc_id", "n", "digest")
    total = rows.agg(F.sum(F.col("n") - F.ceil(F.col("n") * percent / 100) + 1)).first()[0] or 0
    named = docs.filter("doc_id IS NOT NULL")
    postings = named.mapInArrow(returning(_postings(width, percent, sketch, max(256, int(total / BUCKET)))), "bucket int, blob binary, ties binary")
    pairs = postings.groupBy("bucket").applyInPandas(_candidates(percent), _PAIRS)
    pairs = pairs.groupBy("a", "b").agg(F.max("na").alias("na"), F.max("nb").alias("nb"), F.sum("shared").alias("shared"), F.max(F.col("shared").isNull()).alias("tied"))
    most = F.expr(f"shared + ceil({percent} * greatest(na, nb) / 100.0) - 1")
    edges = pairs.filter(F.col("tied") | (most >= F.expr(f"ceil({percent} * (na + nb) / {100.0 + percent})"))).select("a", "b")
    blocks = checkpointed(components(edges))
    bits = power_of_two(16 * blocks.count(), *MEMBER_BITS)
    slot = F.expr(f"pmod(xxhash64(doc_id), {1 << bits})")
    words = np.zeros((1 << bits) // 64, np.uint64)
    taken = blocks.select(F.col("node").alias("doc_id")).select(slot.alias("s")).groupBy((F.col("s") / 64).cast("int").alias("w")).agg(F.expr("bit_or(shiftleft(1L, cast(s % 64 AS int)))").alias("bits"))
    for w, b in taken.collect():  # at most 2**(bits - 6) rows
        words[w] = np.uint64(b & (2**64 - 1))
    bitmap = spark.sparkContext.broadcast(words.tobytes())
    del words
    sets = named.select("doc_id", "text", slot.alias("slot")).mapInArrow(returning(_members(width, bitmap)), "doc_id long, shingles binary")
    # Plan and sets are written: a block's sets are sent once more, to their block or to its cuts.
    sized = checkpointed(sets.join(checkpointed(_planned(blocks, rows)), "doc_id"))
    joined = sized.filter("cuts = 1").select("doc_id", "label", "shingles", F.lit(False).alias("still")).groupBy("label").applyInPandas(_join(percent), "doc_id long, label long")
    labels = joined
    if not (big := sized.filter("cuts > 1")).isEmpty():
        over = components(_cut_blocks(big, percent))
        # A cut block's document outside all classes has no row here, nor does it need one.
        labels = labels.unionByName(over.select(F.col("node").alias("doc_id"), "label"))
    # Written here and in first_of_each_class: one plan from the sets to the texts keeps too many stages in the driver at once.
    labels = checkpointed(labels.groupBy("doc_id").agg(F.min("label").alias("label")))
    kept = rows.filter("n > 0 AND doc_id IS NOT NULL")
    classes = kept.join(labels, "doc_id", "left").groupBy("digest").agg(F.min("doc_id").alias("least"), F.min("label").alias("label"))
    classes = classes.withColumn("label", F.coalesce("label", "least"))
    final = classes.groupBy("label").agg(F.min("least").alias("component_id"))
    found = classes.join(final, "label").select("digest", "component_id")
    return rows.join(found, "digest", "left").select("doc_id", F.col("n").alias("n_shingles"), F.expr("CASE WHEN doc_id IS NOT NULL THEN coalesce(component_id, doc_id) END").alias("component_id"))


def first_of_each_class(docs: DataFrame, percent: int = PERCENT, width: int = WIDTH) -> DataFrame:
    """docs without all but one document of each class: the one whose id names the class."""
    own = checkpointed(link_classes(docs, percent, width).filter("component_id = doc_id").select(F.col("doc_id").alias("__id")).distinct())
    return docs.filter("doc_id IS NULL").unionByName(docs.withColumn("__id", F.col("doc_id").cast("long")).join(own, "__id", "left_semi").drop("__id"))


ORACLE = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_distinct([array_to_string(w[i : i + 4], ' ') FOR i IN range(1, len(w) - 3)]) END AS s FROM words
), flat AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets),
pairs AS (
  SELECT x.doc_id AS a, y.doc_id AS b FROM flat x JOIN flat y ON x.g = y.g AND x.doc_id <> y.doc_id
  GROUP BY x.doc_id, y.doc_id, x.n, y.n HAVING 100 * count(*) >= 75 * (x.n + y.n - count(*))
), reach AS (
  SELECT doc_id AS a, doc_id AS b FROM documents
  UNION SELECT r.a, p.b FROM reach r JOIN pairs p ON r.b = p.a
)
SELECT s.doc_id, len(s.s) AS n_shingles, m.component_id FROM sets s JOIN (SELECT a, min(b) AS component_id FROM reach GROUP BY a) m ON m.a = s.doc_id
"""
