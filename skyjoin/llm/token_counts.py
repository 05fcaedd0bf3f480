"""Token counts of a byte-fallback BPE vocabulary by rank-synchronous merging of ragged numpy arrays.

A text falls into pre-tokens where no piece can cross: before each run of white space, around newlines, and inside long words wherever two
neighbouring characters stand together in no piece. Pre-tokens not met before by this worker form one ragged batch.
In each round every sequence that still has a mergeable pair applies its pair of lowest rank, all sequences at once and all places
of the pair in a sequence from left to right; so a sequence of any length needs about as many rounds as it has ranks. Places behind one
whose piece at once merges on at no higher rank wait. Sequences of LONG symbols or more take the same rounds one by one, in linked arrays
that needn't be packed again. What survives is counted, unknown characters by their UTF-8 bytes.

Edge cases: null and empty texts have no tokens; strings of special tokens are ordinary text; nothing is truncated; rows with the
same id or text are counted one by one; extra columns are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import chunks, returning, texts
from .piece_model import SPACE_MARK, PieceModel, load, normalised
from .tables import NONE, Merges

LIMIT = 4096
#: Counts that a worker keeps; characters from which a word is cut by character pairs; symbols of a sequence that goes alone.
KEPT, CUT, LONG = 300_000, 32, 512
WORDS = re.compile(f"{SPACE_MARK}*[^{SPACE_MARK}\n]+|{SPACE_MARK}+|\n+")


def every_other(start: np.ndarray) -> np.ndarray:
    """Every other place of each run, from its start."""
    number = np.arange(len(start))
    return (number - np.maximum.accumulate(np.where(start, number, 0))) % 2 == 0


class Merger:
    """Vectorised lookup of pairs and counting of pre-tokens for one vocabulary."""

    def __init__(self, model: PieceModel):
        self.merges, self.known = Merges(model), {}
        self.by_point = np.full(0x110000, -1, np.int64)
        self.joins: set[str] = set()
        for p, i in model.ids.items():
            if len(p) == 1:
                self.by_point[ord(p)] = i
            self.joins.update(p[k : k + 2] for k in range(len(p) - 1))

    def ragged(self, words: list[str]) -> np.ndarray:
        """Symbols left in each word after all merges, by rounds over all words at once."""
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        point = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)
        symbol = self.by_point[point]
        owner = np.repeat(np.arange(len(words)), lengths)
        counts = lengths.copy()
        if len(odd := np.flatnonzero(symbol < 0)):  # bytes instead of one symbol
            extra = np.searchsorted(np.array([0x80, 0x800, 0x10000]), point[odd], "right")
            counts += np.bincount(owner[odd], extra, len(words)).astype(np.int64)
        pair = owner[:-1] == owner[1:] if len(owner) else np.zeros(0, bool)
        rank, made = self.merges.look(np.where(pair, symbol[:-1], -1), symbol[1:])
        rank, made = np.append(rank, NONE), np.append(made, 0)
        while True:
            # Only words that still have a pair go on.
            alive = np.unique(owner[rank != NONE])
            if not len(alive):
                return counts
            keep = np.isin(owner, alive) if len(alive) < counts.size else slice(None)
            owner, symbol, rank, made = owner[keep], symbol[keep], rank[keep], made[keep]
            start = np.flatnonzero(np.append(True, owner[1:] != owner[:-1]))
            size = np.diff(np.append(start, len(owner)))
            best = np.minimum.reduceat(rank, start)
            hits = np.flatnonzero(rank == np.repeat(best, size))
            first = hits[self.together(hits, owner, symbol, made, rank)]
            symbol[first] = made[first]
            np.subtract.at(counts, owner[first], 1)
            stay = np.ones(len(owner), bool)
            stay[first + 1] = False
            shift = np.cumsum(stay) - 1
            owner, symbol, rank, made = owner[stay], symbol[stay], rank[stay], made[stay]
            rank, made = rank.copy(), made.copy()
            new = shift[first]
            for at in (new, new[(new > 0)] - 1):
                ok = (at + 1 < len(owner)) & (owner[np.minimum(at + 1, len(owner) - 1)] == owner[at])
                right = np.where(ok, symbol[np.minimum(at + 1, len(owner) - 1)], -1)
                rank[at], made[at] = self.merges.look(symbol[at], right)

    def together(self, hits: np.ndarray, owner: np.ndarray, symbol: np.ndarray, made: np.ndarray, rank: np.ndarray) -> np.ndarray:
        """Which of the places of the lowest rank merge in this round: every other one of a run, up to the first that merges on at once."""
        own = owner[hits]
        start = np.append(True, (own[1:] != own[:-1]) | (hits[1:] != hits[:-1] + 1))
        take = every_other(start)
        if self.merges.hasty[made[hits[take]]].any():
            at = hits[take]
            own, n = owner[at], len(owner)
            joined = np.append(False, (at[1:] == at[:-1] + 2) & (own[1:] == own[:-1]))  # the left neighbour is a place of this round
            left = np.where((at > 0) & (owner[at - 1] == own), symbol[at - 1], -1)
            left = np.where(joined, np.append(-1, made[at[:-1]]), left)
            behind = np.minimum(at + 2, n - 1)
            right = np.where((at + 2 < n) & (owner[behind] == own), symbol[behind], -1)
            take[take] = self.before_haste(left, made[at], right, rank[at], own)
        return take

    def before_haste(self, left: np.ndarray, made: np.ndarray, right: np.ndarray, rank: np.ndarray, own: np.ndarray) -> np.ndarray:
        """Which places may merge at once: those of a sequence up to the first whose new neighbours would go before the others."""
        bad = (self.merges.look(left, made)[0] <= rank) | (self.merges.look(made, right)[0] <= rank)
        earlier = np.cumsum(bad) - bad
        head = np.flatnonzero(np.append(True, own[1:] != own[:-1]))
        return earlier == np.repeat(earlier[head], np.diff(np.append(head, len(own))))

    def lone(self, word: str) -> int:
        """ragged() of one long word: symbols are linked, and those merged away stay where they are."""
        point = np.frombuffer(word.encode("utf-32-le", "surrogatepass"), np.uint32)
        n = len(point)
        symbol = np.append(self.by_point[point], -1)  # the last one stands behind and before the word
        odd = np.flatnonzero(symbol[:-1] < 0)
        count = n + int(np.searchsorted(np.array([0x80, 0x800, 0x10000]), point[odd], "right").sum())
        after, before = np.minimum(np.arange(1, n + 2), n), np.arange(-1, n)
        rank, made = self.merges.look(symbol[:-1], symbol[1:])
        while len(hits := np.flatnonzero(rank == (least := rank.min()))) and least != NONE:
            at = hits[every_other(np.append(True, after[hits[:-1]] != hits[1:]))]
            if self.merges.hasty[made[at]].any():
                left = np.where(np.append(False, before[at[1:]] == after[at[:-1]]), np.append(-1, made[at[:-1]]), symbol[before[at]])
                at = at[self.before_haste(left, made[at], symbol[after[after[at]]], rank[at], np.zeros(len(at)))]
            gone = after[at]
            symbol[at], after[at] = made[at], after[gone]
            symbol[gone], rank[gone] = -1, NONE
            before[after[at]] = at
            count -= len(at)
            for i in (at, before[at][before[at] >= 0]):
                rank[i], made[i] = self.merges.look(symbol[i], symbol[after[i]])
        return count

    def cut(self, word: str) -> list[str]:
        """A long word cut between characters that stand together in no piece."""
        ends = [i + 1 for i in range(len(word) - 1) if word[i : i + 2] not in self.joins]
        return [word[a:b] for a, b in zip([0, *ends], [*ends, len(word)], strict=True)]

    def learn(self, words: set[str]) -> None:
        """Counts for words not met before."""
        parts = {w: self.cut(w) for w in words if len(w) > CUT}
        simple = list({w for w in words if len(w) <= CUT}.union(p for x in parts.values() for p in x if len(p) < LONG))
        counted = dict(zip(simple, self.ragged(simple).tolist(), strict=True)) if simple else {}
        counted.update((p, self.lone(p)) for x in parts.values() for p in x if len(p) >= LONG)
        for w, x in parts.items():
            counted[w] = sum(counted[p] for p in x)
        self.known.update(counted)

    def count(self, batch: list[str]) -> list[int]:
        """Tokens of each text."""
        found = [WORDS.findall(normalised(t)) for t in batch]
        if len(self.known) > KEPT:
            self.known.clear()
        if new := set().union(*found) - self.known.keys():
            self.learn(new)
        known = self.known
        return [sum([known[w] for w in x]) for x in found]


@lru_cache(maxsize=2)
def merger(path: str) -> Merger:
    return Merger(load(path))


def token_counts(docs: DataFrame, path: str, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit of every text under the vocabulary at `path`."""

    def run(batches):
        m = merger(path)
        for whole in batches:
            for batch in chunks(whole, 1):
                body = texts(batch.column(1))
                counts = m.count(body)
                sizes = [len(t.encode()) for t in body]
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(counts, pa.int64()), pa.array([n > limit for n in counts])], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.selectExpr("cast(doc_id AS long) AS doc_id", "text").mapInArrow(returning(run), "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
