"""Toxicity scores from Levenshtein automata intersected with a lexicon trie, and the context of what they find.

The lexicon is learned: words and stems (written "stem*", for all their endings) that toxic texts hold more often than other
sampled ones, by likelihood ratio. The floor is a number of texts, not a share of all toxic ones, so that a language with a small
part of the corpus gets terms too; a term's strength is how much more often toxic texts hold it. Its trie is intersected with the Levenshtein automata of all its terms at once: a state is a set of (trie node, edits so far), made when
first met and kept, so that a word costs one table step a character and most words end in the dead state after a few.
Words allow 0 edits below 4 characters, 1 below 8, else 2, stems none, but full words seen under a stem stand beside it; digits and signs that stand for letters are read as those. Words that
other sampled texts use aren't taken for misspellings.

A hit's weight falls with its edits; within a window of words, quotation marks around it or a verb of reporting beside it lower
it (quotation), a second person or another hit raises it (abuse). A logistic model over a text's sums makes the score.

Training: a bounded sample of labelled rows, SAMPLE rows a label, of up to SAMPLE_BYTES bytes each, by hash. Scores use the text
alone. Edge cases: null and empty texts have no hits and the score of such texts; without labelled rows of both kinds the
lexicon is empty and every score is near 1 (all toxic) or 0; an id with both labels counts as toxic; rows are scored one by one and
equal texts alike; of equally close terms the first listed one is the hit; extra columns are ignored; an empty table gives an empty one.
"""

from __future__ import annotations

import math
import re
import uuid
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, released, returning, texts

WORD = re.compile(r"[^\W_]+(?:[@$!*'][^\W_]+)*")
#: The training sample's bounds; the least likelihood ratio and number of toxic texts of a term.
SAMPLE, SAMPLE_BYTES, LEAST_RATIO, LEAST_TEXTS, MOST_TERMS = 1500, 20_000, 20.0, 3, 5000
#: States that an automaton keeps.
MOST_STATES = 100_000
#: Words on either side that make a hit's context; weight of a hit by its edits; words that a worker keeps.
WINDOW, EDIT_WEIGHT, KEPT = 6, (1.0, 0.8, 0.6), 200_000
THRESHOLD = 0.7
# Signs read as letters; quotation marks; words of reporting and of the second person in the corpus's languages.
SIGNS = str.maketrans("013457@$!", "oieastasi")
QUOTES = "\"'“”„«»‘’‹›"
REPORTING = frozenset("said says quote quoted quotes called word term wrote cited sagte schrieb zitat zitierte wort dijo escribió cita citó palabra dit écrit cite cité citation mot".split())
SECOND = frozenset("you your yours youre du dich dir dein ihr euch tú tu te ti usted ustedes vosotros vous ton ta toi".split())


#: Lengths of stems.
STEMS = range(4, 9)


def most_edits(term: str) -> int:
    return 0 if len(term) < 4 or term.endswith("*") else 1 if len(term) < 8 else 2


class TrieAutomaton:
    """All terms within their own number of edits of a word."""

    def __init__(self, terms: list[str], ordinary: frozenset[str] = frozenset()):
        """ordinary: words that are never misspellings."""
        self.terms, self.ordinary = terms, ordinary
        self.next: list[dict[str, int]] = [{}]
        self.term: list[int] = [-1]
        self.stem: dict[int, int] = {}
        for i, t in enumerate(terms):
            at = 0
            for c in t.removesuffix("*"):
                if c not in self.next[at]:
                    self.next[at][c] = len(self.next)
                    self.next.append({})
                    self.term.append(-1)
                at = self.next[at][c]
            if t.endswith("*"):
                self.stem[at] = i
            else:
                self.term[at] = i
        self.most = [0] * len(self.next)
        for node in range(len(self.next) - 1, -1, -1):
            own = most_edits(terms[self.term[node]]) if self.term[node] >= 0 else 0
            self.most[node] = max([own, *(self.most[k] for k in self.next[node].values())])
        self.letters = {c for x in self.next for c in x}
        self.restart()

    def restart(self) -> None:
        """Forgets all states; they are made again when met."""
        self.states: list[tuple[frozenset[tuple[int, int]], int]] = []
        self.number: dict[tuple[frozenset[tuple[int, int]], int], int] = {}
        self.moves: list[dict[str, int]] = []
        self.best: list[tuple[int, int] | None] = []
        self.dead = self._state({})
        self.start = self._state({0: 0})

    def _state(self, least: dict[int, int], stem: int = -1) -> int:
        """The number of a state, closed under leaving out letters of terms; stem: the stem passed, which holds to the end."""
        work = list(least)
        while work:
            node = work.pop()
            for k in self.next[node].values():
                e = least[node] + 1
                if e <= self.most[k] and e < least.get(k, 99):
                    least[k] = e
                    work.append(k)
        for node, e in least.items():
            if e == 0:  # the longest stem passed
                stem = self.stem.get(node, stem)
        key = (frozenset(least.items()), stem)
        if key not in self.number:
            self.number[key] = len(self.states)
            self.states.append(key)
            self.moves.append({})
            ends = [(e, self.term[n]) for n, e in key[0] if self.term[n] >= 0 and e <= most_edits(self.terms[self.term[n]])]
            ends += [(0, stem)] if stem >= 0 else []
            self.best.append(min(ends) if ends else None)
        return self.number[key]

    def _move(self, state: int, c: str) -> int:
        least: dict[int, int] = {}
        nodes, stem = self.states[state]
        for node, e in nodes:
            kids = self.next[node]
            if e + 1 <= self.most[node]:  # a letter too many, or another one; no child allows more edits than its parent
                least[node] = min(least.get(node, 99), e + 1)
                for k in kids.values():
                    if e + 1 <= self.most[k]:
                        least[k] = min(least.get(k, 99), e + 1)
            if (k := kids.get(c)) is not None and e <= self.most[k]:
                least[k] = min(least.get(k, 99), e)
        return self._state(least, stem)

    def match(self, word: str) -> tuple[int, int] | None:
        """(edits, term number) of the closest term, or None."""
        if self.start == self.dead or word in self.ordinary:
            return None
        if len(self.states) > MOST_STATES:
            self.restart()
        state, moves = self.start, self.moves
        for c in word:
            if c not in self.letters:
                c = ""
            to = moves[state].get(c)
            if to is None:
                to = moves[state][c] = self._move(state, c)
            if to == self.dead:
                return None
            state = to
        return self.best[state]


@dataclass
class Model:
    terms: list[str] = field(default_factory=list)
    strength: list[float] = field(default_factory=list)
    ordinary: frozenset[str] = frozenset()
    weights: list[float] = field(default_factory=lambda: [0.0] * 5)
    constant: float = -9.0


FEATURES = 5


class Scorer:
    def __init__(self, model: Model):
        self.model = model
        self.automaton = TrieAutomaton(model.terms, model.ordinary)
        self.known: dict[str, tuple[int, int] | None] = {}

    def word(self, word: str) -> tuple[int, int] | None:
        """The closer match of a lower-cased word as written and with its signs read as letters."""
        found = self.automaton.match(word)
        if not word.isalpha() and (plain := word.translate(SIGNS)) != word:
            read = self.automaton.match(plain.replace("'", "").replace("*", ""))
            found = min((x for x in (found, read) if x), default=None)
        return found

    def hits(self, text: str) -> list[tuple[int, int, int, float, bool]]:
        """(place of the word, term, edits, weight in context, quoted) of each hit."""
        low = text.lower()
        words = WORD.findall(low)
        known = self.known
        if len(known) > KEPT:
            known.clear()
        wanted = set()
        for w in set(words):
            if w not in known:
                known[w] = self.word(w)
            if known[w] is not None:
                wanted.add(w)
        if not wanted:
            return []
        at = [i for i, w in enumerate(words) if w in wanted]
        out = []
        b = passed = 0
        for n, i in enumerate(at):
            for w in words[passed : i + 1]:  # no word starts between the end of one and the start of the next
                a = low.index(w, b)
                b = a + len(w)
            passed = i + 1
            edits, term = known[words[i]]
            near = words[max(0, i - WINDOW) : i + WINDOW + 1]
            quoted = self.quoted(low, a, b)
            reported = not REPORTING.isdisjoint(near)
            aimed = not SECOND.isdisjoint(near) or (n and i - at[n - 1] <= WINDOW) or (n + 1 < len(at) and at[n + 1] - i <= WINDOW)
            weight = self.model.strength[term] * EDIT_WEIGHT[edits] * (0.4 if quoted else 1.0) * (0.7 if reported else 1.0) * (1.3 if aimed else 1.0)
            out.append((i, term, edits, weight, quoted))
        return out

    @staticmethod
    def quoted(text: str, start: int, end: int) -> bool:
        """Whether a quotation mark opens before and one closes after the word in its line, within 80 characters."""
        left, right = text[max(0, start - 80) : start].rpartition("\n")[2], text[end : end + 80].partition("\n")[0]
        opened = [k for k, c in enumerate(left) if c in QUOTES and (k + 1 == len(left) or not left[k + 1].isspace())]
        closed = [k for k, c in enumerate(right) if c in QUOTES and (k == 0 or not right[k - 1].isspace())]
        return bool(opened and closed) and sum(c in QUOTES for c in left) % 2 == 1

    @staticmethod
    def features(text: str, hits: list[tuple[int, int, int, float, bool]]) -> list[float]:
        """What the logistic model reads of a text's hits."""
        if not hits:
            return [0.0] * FEATURES
        exact, fuzzy = (sum(h[3] for h in hits if bool(h[2]) == kind) for kind in (False, True))
        top = max((h[3] for h in hits if not h[2]), default=0.0)
        return [math.log1p(exact), math.log1p(fuzzy), top, min(1.0, 100 * exact / (len(text) / 6 + 1)), sum(h[4] for h in hits) / len(hits)]

    def score(self, x: list[float]) -> float:
        z = self.model.constant + sum(a * b for a, b in zip(self.model.weights, x, strict=True))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def _ratio(a: int, na: int, b: int, nb: int) -> float:
    """Log-likelihood ratio of a term in a of na toxic and b of nb other texts."""
    p = (a + b) / (na + nb)
    out = 0.0
    for k, n in ((a, na), (b, nb)):
        for x, e in ((k, n * p), (n - k, n * (1 - p))):
            out += 2 * x * math.log(x / e) if x else 0.0
    return out


def train(rows: list[tuple[str, int]]) -> Model:
    """A model from (text, toxic) rows."""
    n = Counter(y for _, y in rows)
    if not n[0] or not n[1]:
        return Model(constant=9.0 if n[1] else -9.0)
    held = {0: Counter(), 1: Counter()}
    for text, y in rows:
        words = {w for w in WORD.findall((text or "").lower()) if w.isalpha() and len(w) > 2}
        held[y].update(words.union(w[:k] + "*" for w in words for k in STEMS if len(w) > k))
    scored = []
    for w, a in held[1].items():
        b = held[0][w]
        if a >= LEAST_TEXTS and a / n[1] > (b + 0.5) / n[0] and (r := _ratio(a, n[1], b, n[0])) >= LEAST_RATIO:
            scored.append((-round(r, 6), w.endswith("*"), -len(w), w, math.log(a / n[1] / ((b + 0.5) / n[0]))))
    terms: list[str] = []
    strength: list[float] = []
    starts: dict[str, int] = {}  # of all terms taken, to the most toxic texts of one
    for _, _, _, w, odds in sorted(scored):
        body = w.removesuffix("*")
        # A wider stem than a term taken must hold in more texts than that term, by the floor.
        if len(terms) < MOST_TERMS and (body not in starts or w.endswith("*") and held[1][w] >= starts[body] + LEAST_TEXTS) and not any(body[:k] + "*" in terms for k in STEMS if k <= len(body)):
            terms.append(w)
            strength.append(min(1.0, odds / math.log(500)))
            starts.update((body[:k], max(held[1][w], starts.get(body[:k], 0))) for k in range(1, len(body) + 1))
    # A stem itself allows no edits, as it may end in anything; the full words seen under it stand beside it with their own.
    stems = {t for t in terms if t.endswith("*")}
    for w, a in sorted(held[1].items(), key=lambda x: (-x[1], x[0])):
        rate, b = a / n[1], held[0][w]
        if len(terms) < MOST_TERMS and a >= LEAST_TEXTS and rate > (b + 0.5) / n[0] and not w.endswith("*") and any(w[:k] + "*" in stems for k in STEMS):
            terms.append(w)
            strength.append(min(1.0, math.log(rate / ((b + 0.5) / n[0])) / math.log(500)))
    plain = TrieAutomaton(terms)
    near = {w for w in held[0] if not w.endswith("*") and (m := plain.match(w)) and m[0]}
    # The weights are fitted on texts whose own words didn't count as ordinary, as with texts outside the sample: half by half.
    halves = [set(), set()]
    for i, (text, y) in enumerate(rows):
        if not y:
            halves[i % 2].update(near.intersection(WORD.findall((text or "").lower())))
    scorers = [Scorer(Model(terms, strength, frozenset(halves[1 - k]))) for k in (0, 1)]
    x = np.array([[1.0, *Scorer.features(t or "", scorers[i % 2].hits(t or ""))] for i, (t, _) in enumerate(rows)])
    ordinary = frozenset(near)
    y = np.array([k for _, k in rows], float)
    w = np.zeros(x.shape[1])
    for _ in range(25):  # Newton's method with a penalty
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        hessian = (x * (p * (1 - p))[:, None]).T @ x + np.diag([1e-6, *[0.05] * FEATURES])
        w += np.linalg.solve(hessian, x.T @ (y - p) - np.array([0.0, *[0.05] * FEATURES]) * w)
    return Model(terms, strength, ordinary, w[1:].tolist(), float(w[0]))


def trainable() -> F.Column:
    """Rows whose labels may be learned from."""
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(3)) != 1


def sample(docs: DataFrame, labels: DataFrame, per_label: int = SAMPLE) -> list[tuple[str, int]]:
    """(text, toxic) of at most per_label rows of each label, by hash of the id; ids with both labels count as toxic."""
    known = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    counts = {r.toxic: r.n for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    part = F.pmod(F.xxhash64("doc_id", F.lit(23)), F.lit(1 << 30)) / float(1 << 30)
    share = F.when(F.col("toxic") == 1, min(1.0, 1.15 * per_label / max(1, counts.get(1, 0)))).otherwise(min(1.0, 1.15 * per_label / max(1, counts.get(0, 0))))
    chosen = known.withColumn("at", part).filter(F.col("at") < share)  # about 1.15 per_label ids a label: broadcast
    rows = docs.filter(F.octet_length("text") <= SAMPLE_BYTES).select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
    out: dict[int, list[str]] = {0: [], 1: []}
    for r in sorted(rows.select("at", "doc_id", "toxic", "text").collect(), key=lambda r: (r.at, r.doc_id, r.text)):
        if len(out[int(r.toxic == 1)]) < per_label:
            out[int(r.toxic == 1)].append(r.text)
    return [(t, y) for y in (0, 1) for t in out[y]]


#: The scorer of a worker, by the call that made its model: the next task of that call goes on with its states.
_SCORERS: dict[str, Scorer] = {}


def scorer_of(call: str, model: Model) -> Scorer:
    """This worker's scorer for a call; that of an earlier call goes."""
    if call not in _SCORERS:
        _SCORERS.clear()
        _SCORERS[call] = Scorer(model)
    return _SCORERS[call]


def score_texts(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score, n_hits, n_fuzzy, n_quoted and the terms found, of docs (doc_id, text)."""
    shipped, call = docs.sparkSession.sparkContext.broadcast(model), uuid.uuid4().hex
    schema = "doc_id long, score double, n_hits int, n_fuzzy int, n_quoted int, terms array<string>"

    def run(batches):
        scorer = scorer_of(call, shipped.value)
        for whole in batches:
            for batch in chunks(whole, 1):
                rows = []
                for text in texts(batch.column(1)):
                    hits = scorer.hits(text)
                    rows.append((scorer.score(scorer.features(text, hits)), len(hits), sum(h[2] > 0 for h in hits), sum(h[4] for h in hits), sorted({scorer.model.terms[h[1]] for h in hits})))
                columns = list(zip(*rows, strict=True)) or [[]] * 5
                kinds = (pa.float64(), pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.string()))
                yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], ["doc_id", "score", "n_hits", "n_fuzzy", "n_quoted", "terms"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(returning(run), schema)


def toxicity_report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """What op1 returns: doc_id, held_out, score, predicted and counts of hits. Held-out labels are never read."""
    model = train(sample(docs, labels.filter(trainable()).select("doc_id", "toxic")))
    released()
    scored = score_texts(docs, model)
    return scored.select("doc_id", (~trainable()).alias("held_out"), "score", F.when(F.col("score") >= THRESHOLD, 1).otherwise(0).alias("predicted"), "n_hits", "n_fuzzy", "n_quoted", "terms")
