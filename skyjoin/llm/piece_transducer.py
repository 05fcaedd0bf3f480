"""Encoding and decoding with a byte-fallback piece vocabulary as a weighted finite-state transducer.

Weights are of the tropical semiring: they add up along a path, and the least path counts. Four machines are compiled:

* the normaliser: an arc without input that writes one mark in front, then a state whose arcs rewrite white space to marks and
  every other character to itself, all of weight 0;
* the pieces: a trie of (state, character) arcs; a piece's end writes its number and costs the piece's weight;
* byte fallback: a character that is no piece writes the numbers of its bytes, each at a weight of its own;
* an acceptor over pairs of neighbouring pieces with their weights. For a vocabulary of merges the pair costs 0 if merging its joined
  text gives the pair back, else infinity; with 1 a piece the least path is then the library's own segmentation.

Composed with an input they are a lattice of states (position, last piece). Distances are relaxed in the order of positions, for all
parts of a batch at once; the path is read back from the least final state. Inputs fall apart where no piece can cross (white
space after text, newlines); each part is composed once per worker while it is remembered. Parts of LONG characters or more are
relaxed one by one, by the same recurrence.

Edge cases: null and empty texts have no ids; a part of any length is composed whole; a part without a path of finite weight
is spelled by its bytes; strings of special tokens are ordinary text; decoding drops the leading mark alone and replaces invalid
bytes by U+FFFD; repeated rows are encoded alike; extra columns stay, one called as an output is replaced.
"""

from __future__ import annotations

import hashlib
import math
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import chunks, returning, texts, with_fields
from .piece_model import SPACE_MARK, PieceModel, load
from .tables import NONE, Merges, Table, pair_key
from .token_counts import WORDS

#: Parts that a worker keeps, of fewer than LONG characters; pairs that it keeps.
KEPT, LONG, PAIRS = 200_000, 64, 600_000
#: The weight of a byte of a character that is no piece.
BYTE = 10.0


class Normaliser:
    """Arcs that rewrite single characters, after one without input at the start of a text that isn't empty."""

    def __init__(self, start: str, arcs: dict[str, str]):
        if any(c in out for out in arcs.values() for c in arcs):
            raise ValueError("an arc writes what another one reads")
        self.start, self.arcs = start, arcs

    def compose(self, text: str) -> str:
        """What the one path writes: the arcs read different characters, so they may pass one after another."""
        for c, out in self.arcs.items():
            text = text.replace(c, out)
        return self.start + text if text else ""


class MergePairs:
    """The pair acceptor of a vocabulary of merges."""

    def __init__(self, model: PieceModel):
        self.pieces, self.rank, self.merges = model.pieces, model.rank, Merges(model)
        self.known = Table(PAIRS)
        n = model.size
        # The last merge of each piece, and its rank: -1 for a character.
        self.left, self.right, self.formed = np.full(n, -1, np.int64), np.full(n, -1, np.int64), np.full(n, -1, np.int64)
        self.whole, self.odd = np.zeros(n, bool), np.zeros(n, bool)
        for p, i in model.ids.items():
            part, last = self.merged(p)
            self.whole[i] = part == [p]
            if last and self.whole[i]:
                self.left[i], self.right[i], self.formed[i] = model.ids[last[0]], model.ids[last[1]], model.rank[p]
        # Where a part was formed no earlier than the whole, ranks don't tell the order of merges.
        deep = np.flatnonzero(self.left >= 0)
        self.odd[deep] = np.maximum(self.formed[self.left[deep]], self.formed[self.right[deep]]) >= self.formed[deep]

    def merged(self, text: str) -> tuple[list[str], tuple[str, str] | None]:
        """What the merges make of a short text, lowest rank and leftmost first, and the last merge: the definition."""
        part, rank, last = list(text), self.rank, None
        while len(part) > 1:
            best, at = None, -1
            for i in range(len(part) - 1):
                r = rank.get(part[i] + part[i + 1])
                if r is not None and (best is None or r < best):
                    best, at = r, i
            if best is None:
                break
            last = (part[at], part[at + 1])
            part[at : at + 2] = [part[at] + part[at + 1]]
        return part, last

    def one(self, a: int, b: int) -> float:
        x, y = self.pieces[a], self.pieces[b]
        return 0.0 if self.merged(x + y)[0] == [x, y] else math.inf

    def weights(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Weights of pairs of pieces; a negative number, of a character's bytes or the start, stands beside anything."""
        out = np.zeros(len(a))
        both = np.flatnonzero((a >= 0) & (b >= 0))
        key = pair_key(a[both], b[both])
        found = self.known.get(key)
        if len(new := np.flatnonzero(found < 0)):
            fresh, back = np.unique(key[new], return_inverse=True)
            bad = self.crossed((fresh >> np.uint64(32)).astype(np.int64), (fresh & np.uint64(2**32 - 1)).astype(np.int64))
            if self.known.full(len(fresh)):
                self.known.clear()
            if not self.known.full(len(fresh)):
                self.known.put(fresh, bad.astype(np.int32))
            found[new] = bad[back]
        out[both[found > 0]] = math.inf
        return out

    def crossed(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Whether a merge across the border comes before both pieces are whole.

        The parts at the border are followed back in time, undoing the later merge of the two sides: two of them that stood side by
        side would have merged if their rank came before the merge that took either one (on a tie the leftmost pair goes first).
        """
        bad, todo = np.zeros(len(a), bool), np.arange(len(a))
        odd = self.odd[a] | self.odd[b]
        for i in np.flatnonzero(odd):
            bad[i] = self.one(int(a[i]), int(b[i])) > 0
        todo = todo[~odd]
        u, v = a[todo], b[todo]
        over_u, over_v = np.full(len(todo), NONE, np.int64), np.full(len(todo), NONE, np.int64)
        while len(todo):
            rank = self.merges.look(u, v)[0]
            hit = (rank < over_u) & (rank <= over_v) & (rank != NONE)
            bad[todo[hit]] = True
            fu, fv = self.formed[u], self.formed[v]
            on = ~hit & (np.maximum(fu, fv) >= 0)
            todo, u, v, over_u, over_v, fu, fv = (x[on] for x in (todo, u, v, over_u, over_v, fu, fv))
            later = fv >= fu
            over_u, over_v = np.where(later, over_u, fu), np.where(later, fv, over_v)
            u, v = np.where(later, u, self.right[u]), np.where(later, self.left[v], v)
        return bad


class Transducer:
    """The machines of one vocabulary. pieces: text to (number, weight); pairs: an acceptor with weights() and one(), or None."""

    def __init__(self, pieces: dict[str, tuple[int, float]], byte_ids: list[int], size: int, pairs=None, normaliser: Normaliser | None = None, byte: float = BYTE):
        self.pieces, self.byte_ids, self.pairs, self.byte = pieces, np.array(byte_ids), pairs, byte
        self.normaliser = normaliser or Normaliser(SPACE_MARK, {" ": SPACE_MARK})
        self.weight, self.longest = np.zeros(size), max(map(len, pieces), default=1)
        states: dict[tuple[int, int], int] = {}
        ends = [-1]
        for piece, (number, weight) in pieces.items():
            at = 0
            for c in piece:
                to = states.get((at, ord(c)))
                if to is None:
                    to = states[at, ord(c)] = len(ends)
                    ends.append(-1)
                at = to
            ends[at], self.weight[number] = number, weight
        self.ends = np.array(ends)
        self.arcs = Table(len(states))
        if states:
            self.arcs.put(pair_key(*np.array(list(states)).T), np.array(list(states.values()), np.int32))
        self.known: dict[str, bytes] = {}
        self.spelled: list[bytes] = [b""] * size
        for piece, (number, _) in pieces.items():
            self.spelled[number] = piece.replace(SPACE_MARK, " ").encode("utf-8", "surrogatepass")
        for b, number in enumerate(byte_ids):
            self.spelled[number] = bytes([b])

    def fallback(self, c: str) -> list[int]:
        return [int(self.byte_ids[b]) for b in c.encode("utf-8", "surrogatepass")]

    def lattice(self, point: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Start, length, number and weight of all arcs over code points, whose parts end before `ends`; fallback arcs have number -1."""
        alive, state = np.arange(len(point)), np.zeros(len(point), np.int64)
        starts, lengths, numbers = [], [], []
        for k in range(self.longest):
            state = self.arcs.get(pair_key(state, point[alive + k])).astype(np.int64)
            on = state >= 0
            alive, state = alive[on], state[on]
            done = self.ends[state] >= 0
            starts.append(alive[done])
            lengths.append(np.full(int(done.sum()), k + 1))
            numbers.append(self.ends[state[done]])
            on = alive + k + 1 < ends[alive]
            alive, state = alive[on], state[on]
            if not len(alive):
                break
        single = np.zeros(len(point), bool)
        single[starts[0]] = True
        other = np.flatnonzero(~single)
        bytes_ = 1 + np.searchsorted(np.array([0x80, 0x800, 0x10000]), point[other], "right")
        weights = [self.weight[n] for n in numbers]
        return (
            np.concatenate([*starts, other]), np.concatenate([*lengths, np.ones(len(other), np.int64)]),
            np.concatenate([*numbers, np.full(len(other), -1)]), np.concatenate([*weights, self.byte * bytes_]),
        )

    def shortest(self, parts: list[str]) -> list[list[int]]:
        """Numbers on the least path of each part (none empty), all parts relaxed together position by position."""
        size = np.fromiter(map(len, parts), np.int64, len(parts))
        first = np.cumsum(size) - size
        owner = np.repeat(np.arange(len(parts)), size)
        point = np.frombuffer("".join(parts).encode("utf-32-le", "surrogatepass"), np.uint32)
        start, length, number, weight = self.lattice(point, (first + size)[owner])
        place = start - first[owner[start]]
        order = np.lexsort((start, place))
        start, length, number, weight, place = start[order], length[order], number[order], weight[order], place[order]
        count = np.bincount(start, minlength=len(point))
        of = np.zeros(len(point), np.int64)
        head = np.flatnonzero(np.append(True, start[1:] != start[:-1]))
        of[start[head]] = head  # the first arc of each position
        # States by the position that they stand at; each has its part, arc, distance and the state before.
        arc, back = [np.full(len(parts), -1)], [np.full(len(parts), -1)]
        held: dict[int, list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]] = {0: [(np.arange(len(parts)), np.arange(len(parts)), arc[0], np.zeros(len(parts)))]}
        total = len(parts)
        final_id, final_far = np.full(len(parts), -1), np.full(len(parts), math.inf)
        for at in range(int(size.max(initial=0)) + 1):
            if at not in held:
                continue
            ids, own, last, d = (np.concatenate(x) for x in zip(*held.pop(at), strict=True))
            if self.pairs is None:  # the last piece doesn't matter: the least state of each part goes on
                o = np.lexsort((ids, d, own))
                o = o[np.append(True, own[o][1:] != own[o][:-1])]
                ids, own, last, d = ids[o], own[o], last[o], d[o]
            ended = size[own] == at
            if ended.any():
                e, f, g = own[ended], d[ended], ids[ended]
                o = np.lexsort((g, f, e))
                o = o[np.append(True, e[o][1:] != e[o][:-1])]
                final_id[e[o]], final_far[e[o]] = g[o], f[o]
            ids, own, last, d = ids[~ended], own[~ended], last[~ended], d[~ended]
            if not len(ids):
                continue
            here = first[own] + at
            n = count[here]
            rep = np.repeat(np.arange(len(ids)), n)
            arcs = of[here][rep] + np.arange(len(rep)) - np.repeat(np.cumsum(n) - n, n)
            new = d[rep] + weight[arcs]
            if self.pairs is not None:
                before = np.where(last >= 0, number[last], -1)
                new = new + self.pairs.weights(before[rep], number[arcs])
                ok = np.isfinite(new)
                rep, arcs, new = rep[ok], arcs[ok], new[ok]
            o = np.lexsort((rep, new, arcs))  # the least way to each state
            o = o[np.append(True, arcs[o][1:] != arcs[o][:-1])] if len(o) else o
            rep, arcs, new = rep[o], arcs[o], new[o]
            fresh = total + np.arange(len(arcs))
            total += len(arcs)
            arc.append(arcs)
            back.append(ids[rep])
            to = at + length[arcs]
            for k in np.unique(to):
                m = to == k
                held.setdefault(int(k), []).append((fresh[m], own[rep][m], arcs[m], new[m]))
        arc_all, back_all = np.concatenate(arc), np.concatenate(back)
        out: list[list[int]] = [[] for _ in parts]
        steps: list[tuple[np.ndarray, np.ndarray]] = []
        live, state = np.flatnonzero(final_id >= 0), final_id[final_id >= 0]
        while len(live):
            on = arc_all[state] >= 0
            live, state = live[on], state[on]
            steps.append((live, arc_all[state]))
            state = back_all[state]
        if steps:
            owners, taken = np.concatenate([s[0] for s in reversed(steps)]), np.concatenate([s[1] for s in reversed(steps)])
            o = np.argsort(owners, kind="stable")
            owners, numbers, places = owners[o], number[taken[o]], start[taken[o]]
            bounds = np.searchsorted(owners, np.arange(len(parts) + 1))
            flat, odd = numbers.tolist(), numbers.min(initial=0) < 0
            for k, (a, b) in enumerate(zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)):
                out[k] = flat[a:b]
                if odd and min(out[k], default=0) < 0:
                    out[k] = [i for j in range(a, b) for i in ([flat[j]] if flat[j] >= 0 else self.fallback(chr(point[places[j]])))]
        for k in np.flatnonzero(final_id < 0):
            out[k] = self.fallback(parts[k])
        return out

    def shortest_one(self, text: str) -> list[int]:
        """The same for one part of any length, state by state."""
        n = len(text)
        best: list[dict[int, tuple[float, int, int]]] = [{} for _ in range(n + 1)]  # last piece to distance, start, piece before
        best[0][-2] = (0.0, 0, -2)
        for at in range(n):
            states = best[at]
            if self.pairs is None and states:
                least = min(states, key=lambda k: (states[k][0], k))
                states = {least: states[least]}
            if not states:
                continue
            arcs = [(k, *found) for k in range(1, min(self.longest, n - at) + 1) if (found := self.pieces.get(text[at : at + k]))]
            if not arcs or arcs[0][0] > 1:
                arcs.append((1, -1, self.byte * len(self.fallback(text[at]))))
            for last, (d, _, _) in states.items():
                for k, number, weight in arcs:
                    new = d + weight + (self.pair(last, number) if self.pairs is not None and last >= 0 and number >= 0 else 0.0)
                    if new < math.inf and new < best[at + k].get(number, (math.inf,))[0]:
                        best[at + k][number] = (new, at, last)
        if not best[n]:
            return self.fallback(text)
        out: list[int] = []
        end, last = n, min(best[n], key=lambda k: (best[n][k][0], k))
        while end:
            _, at, before = best[end][last]
            out += [last] if last >= 0 else reversed(self.fallback(text[at]))
            end, last = at, before
        return out[::-1]

    @lru_cache(maxsize=100_000)  # noqa: B019 (as many transducers as vocabularies)
    def pair(self, a: int, b: int) -> float:
        return self.pairs.one(a, b)

    def packed(self, batch: list[str]) -> list[bytes]:
        """Numbers of each text as 32-bit integers."""
        found = [WORDS.findall(self.normaliser.compose(t)) for t in batch]
        if len(self.known) > KEPT:
            self.known.clear()
        new = set().union(*found) - self.known.keys()
        long = {p: np.array(self.shortest_one(p), np.int32).tobytes() for p in new if len(p) >= LONG}
        short = [p for p in new if len(p) < LONG]
        known = self.known
        for k in range(0, len(short), 1 << 14):
            some = short[k : k + (1 << 14)]
            ids = self.shortest(some)
            flat = np.array([i for x in ids for i in x], np.int32).tobytes()
            at = 0
            for p, x in zip(some, ids, strict=True):
                known[p] = flat[at : (at := at + 4 * len(x))]
        if long:
            known = known | long
        return [b"".join([known[p] for p in x]) for x in found]

    def encode(self, batch: list[str]) -> list[list[int]]:
        """Numbers of each text."""
        return [np.frombuffer(x, np.int32).tolist() for x in self.packed(batch)]

    def decode(self, ids: list[int]) -> str:
        """The text of a list of numbers."""
        body = b"".join(map(self.spelled.__getitem__, ids))
        return (body[1:] if body.startswith(b" ") else body).decode("utf-8", "replace")


def of_model(model: PieceModel) -> Transducer:
    """The transducer of a vocabulary of merges: a weight of 1 for each piece that merging can make."""
    pairs = MergePairs(model)
    pieces = {p: (i, 1.0) for p, i in model.ids.items() if pairs.whole[i]}
    out = Transducer(pieces, model.byte_ids, model.size, pairs)
    for p, i in model.ids.items():  # decoding knows every piece
        out.spelled[i] = p.replace(SPACE_MARK, " ").encode()
    for i, p in enumerate(model.pieces):
        out.spelled[i] = out.spelled[i] or p.encode()
    return out


@lru_cache(maxsize=2)
def transducer(path: str) -> Transducer:
    return of_model(load(path))


def _lists(packed: list[bytes]) -> pa.Array:
    offsets = np.concatenate(([0], np.cumsum([len(x) // 4 for x in packed]))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.frombuffer(b"".join(packed), np.int32)))


def encode_texts(docs: DataFrame, path: str) -> DataFrame:
    """docs with ids array<int> of text; an input column of that name is replaced."""
    schema = with_fields(docs.schema, [T.StructField("ids", T.ArrayType(T.IntegerType(), False))])
    names = schema.names[:-1]

    def run(batches):
        t = transducer(path)
        for whole in batches:
            at = whole.schema.get_field_index("text")
            for batch in chunks(whole, at):
                ids = _lists(t.packed(texts(batch.column(at))))
                yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(n)) for n in names), ids], [*names, "ids"])

    return docs.mapInArrow(returning(run), schema)


def decode_texts(encoded: DataFrame, path: str) -> DataFrame:
    """encoded (with ids) with decoded string of ids; null ids give a null text."""
    schema = with_fields(encoded.schema, [T.StructField("decoded", T.StringType())])
    names = schema.names[:-1]

    def run(batches):
        t = transducer(path)
        for batch in batches:
            body = [None if x is None else t.decode(x) for x in batch.column(batch.schema.get_field_index("ids")).to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(n)) for n in names), pa.array(body, pa.string())], [*names, "decoded"])

    return encoded.mapInArrow(returning(run), schema)


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_chars, n_ids, ids, and the digest of the text decoded from ids with whether it equals the text."""

    def run(batches):
        t = transducer(path)
        for whole in batches:
            for batch in chunks(whole, 1):
                body = texts(batch.column(1))
                packed = t.packed(body)
                back = [t.decode(np.frombuffer(x, np.int32).tolist()) for x in packed]
                columns = [pa.array([len(x) for x in body], pa.int64()), pa.array([len(x) // 4 for x in packed], pa.int64()), _lists(packed), pa.array([hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest() for x in back]), pa.array([x == y for x, y in zip(body, back, strict=True)])]
                yield pa.RecordBatch.from_arrays([batch.column(0), *columns], ["doc_id", "n_chars", "n_ids", "ids", "decoded_sha256", "lossless"])

    return docs.selectExpr("cast(doc_id AS long) AS doc_id", "text").mapInArrow(returning(run), "doc_id long, n_chars long, n_ids long, ids array<int>, decoded_sha256 string, lossless boolean")
