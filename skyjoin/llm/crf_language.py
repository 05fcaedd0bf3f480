"""Word-level language identification with a linear-chain conditional random field; a text's language is its words' vote.

A word's emission is the sum of learned weights of its features: affixes, character n-grams, whether it stands in a learned
lexicon of a language, its script. Learned transitions say how languages follow one another. Forward-backward gives each
word's label probabilities; their sums over the text give the text's label and score. Code-switched passages keep their own
labels (label_words).

Training: a bounded sample of distinct labelled texts (exactly PER_LABEL a label at most, of the first SAMPLE_CHARS characters each,
by hash of the text, so that copies count once and no label is lost), cut into pieces that are chained at random, so that switches
occur; weights by full-batch Adagrad on the exact gradient, whose size by round the model keeps.
Inference runs over all words of whole texts, in segments: transfer matrices of all segments together, then the few
segments of each text in order, then all words together.

Edge cases: null texts and texts without a letter are "und" with score 0; with no labelled row at all every text is "und"; equal
texts have equal predictions; rows are predicted one by one, whatever their id; extra columns are ignored; an empty table gives an
empty one; shares that are equal go to the first label in alphabetical order.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import chunks, released, returning, texts

WORD = re.compile(r"[^\W\d_]+")
UNKNOWN = "und"
#: The training sample's bounds.
PER_LABEL, SAMPLE_CHARS = 150, 20_000
#: Feature slots as a power of two; lexicon words a label; pieces' words and pieces a sequence; rounds; penalty; step.
SLOTS, LEXICON, PIECE, CHAIN, ROUNDS, PENALTY, STEP = 16, 300, 16, 4, 20, 1e-3, 0.5
#: Words of a segment in inference; words that a worker keeps.
SEGMENT, KEPT = 64, 200_000


def _slots(*parts: np.ndarray, kind: int) -> np.ndarray:
    """A slot for each row of some aligned arrays of code points."""
    with np.errstate(over="ignore"):
        h = np.full(len(parts[0]), kind * 2 + 1, np.uint64)
        for p in parts:
            h = (h ^ p.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(29)
        return (h * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(64 - SLOTS)).astype(np.int64)


def features(words: list[str], lexicon: dict[str, list[int]]) -> tuple[np.ndarray, np.ndarray]:
    """(word number, slot) of all features of lower-cased words: affixes, n-grams, lexicons, script, length, a constant."""
    lengths = np.fromiter(map(len, words), np.int64, len(words)) + 2
    point = np.frombuffer("".join(f"^{w}$" for w in words).encode("utf-32-le", "surrogatepass"), np.uint32)
    owner, number = np.repeat(np.arange(len(words)), lengths), np.arange(len(words))
    start, end = np.cumsum(lengths) - lengths, np.cumsum(lengths)
    found = [(number, _slots(np.zeros(len(words)), kind=0)), (number, _slots(np.minimum(lengths, 14), kind=1)), (number, _slots(point[start + 1] >> 7, kind=2))]
    for k in (2, 3):
        at = np.flatnonzero(owner[: len(owner) - k + 1] == owner[k - 1 :])
        found.append((owner[at], _slots(*(point[at + j] for j in range(k)), kind=2 + k)))
    for k in (1, 2, 3, 4):
        own = np.flatnonzero(lengths - 2 >= k)
        if k < 4:
            found.append((own, _slots(*(point[start[own] + 1 + j] for j in range(k)), kind=10 + k)))
        found.append((own, _slots(*(point[end[own] - 2 - j] for j in range(k)), kind=20 + k)))
    listed = [(i, y) for i, w in enumerate(words) if w in lexicon for y in lexicon[w]]
    if listed:
        i, y = np.array(listed).T
        found.append((i, _slots(y, kind=30)))
    return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])


def summed(owner: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Rows of values added up by owner."""
    return np.stack([np.bincount(owner, values[:, y], n) for y in range(values.shape[1])], axis=1)


@dataclass
class Model:
    labels: list[str]
    weights: np.ndarray  # slots x labels
    transitions: np.ndarray  # labels x labels, logarithms
    lexicon: dict[str, list[int]]
    gradients: list[float] = field(default_factory=list)  # the length of the gradient by round


def forward_backward(emission: np.ndarray, mask: np.ndarray, step: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Marginals, log partition and expected transitions of padded sequences; emission is logarithmic, step a matrix of factors."""
    s, t, k = emission.shape
    peak = emission.max(axis=2, keepdims=True)
    e = np.exp(emission - peak)
    alpha, scale = np.empty((s, t, k)), np.ones((s, t))
    for i in range(t):
        a = e[:, i] if not i else (alpha[:, i - 1] @ step) * e[:, i]
        z = a.sum(axis=1)
        if i:
            a, z = np.where(mask[:, i, None], a, alpha[:, i - 1]), np.where(mask[:, i], z, 1.0)
        scale[:, i] = z
        alpha[:, i] = a / (a.sum(axis=1, keepdims=True))
    beta = np.ones((s, t, k))
    pairs = np.zeros((k, k))
    for i in range(t - 2, -1, -1):
        on = mask[:, i + 1]
        right = e[:, i + 1] * beta[:, i + 1] / scale[:, i + 1, None]
        beta[:, i] = np.where(on[:, None], right @ step.T, beta[:, i + 1])
        pairs += np.einsum("sa,sb->ab", alpha[:, i] * on[:, None], right) * step
    post = alpha * beta
    post /= post.sum(axis=2, keepdims=True)
    return post, (np.log(scale) * mask).sum() + (peak[..., 0] * mask).sum(), pairs


def sample(docs: DataFrame, per_label: int = PER_LABEL) -> list[tuple[str, str]]:
    """(text, lang) of at most per_label distinct texts of each label: what reaches the driver."""
    rows = docs.filter(F.col("lang").isNotNull() & (F.length("text") > 0)).select("lang", F.substring("text", 1, SAMPLE_CHARS).alias("text"))
    rows = rows.withColumn("at", F.xxhash64("text", F.lit(17)))
    counts = rows.select("lang", "at").distinct().groupBy("lang").agg(F.count("*").alias("n"))
    # About 1.25 per_label texts of a label lie below its cut; all of them if there are no more. Then the exact ones.
    part = F.pmod("at", F.lit(1 << 30)) / float(1 << 30)
    found = rows.join(F.broadcast(counts), "lang").filter(part * F.col("n") < per_label * 1.25 + 40).groupBy("lang", "at").agg(F.min("text").alias("text"))
    found = found.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.pmod("at", F.lit(1 << 30)), "at", "text"))).filter(F.col("r") <= per_label)
    return [(r.text, r.lang) for r in found.orderBy("lang", "r").select("text", "lang").collect()]


def train(rows: list[tuple[str, str]], seed: int = 5) -> Model:
    labels = sorted({k for _, k in rows})
    if not labels:
        return Model([], np.zeros((1 << SLOTS, 0), np.float32), np.zeros((0, 0)), {})
    k, rng = len(labels), np.random.default_rng(seed)
    counts: list[dict[str, int]] = [{} for _ in labels]
    pieces: list[tuple[int, list[str]]] = []
    for text, lang in rows:
        y, words = labels.index(lang), [w for w in WORD.findall(text.lower()) if w.isalpha()]
        for w in words:
            counts[y][w] = counts[y].get(w, 0) + 1
        pieces += [(y, words[i : i + PIECE]) for i in range(0, len(words), PIECE)]
    lexicon: dict[str, list[int]] = {}
    for y, own in enumerate(counts):
        for w in sorted(own, key=lambda w: (-own[w], w))[:LEXICON]:
            lexicon.setdefault(w, []).append(y)
    order = rng.permutation(len(pieces))
    chains = [order[i : i + CHAIN] for i in range(0, len(order), CHAIN)]
    index: dict[str, int] = {}
    t = PIECE * CHAIN
    ids, gold, mask = np.zeros((len(chains), t), np.int64), np.zeros((len(chains), t), np.int64), np.zeros((len(chains), t), bool)
    for s, chain in enumerate(chains):
        at = 0
        for p in chain:
            y, words = pieces[p]
            for w in words:
                ids[s, at], gold[s, at], mask[s, at] = index.setdefault(w, len(index)), y, True
                at += 1
    owner, flat = features(list(index), lexicon)
    weights, trans = np.zeros((1 << SLOTS, k)), np.zeros((k, k))
    past, past_t = np.full((1 << SLOTS, k), 1e-8), np.full((k, k), 1e-8)
    n = max(1, int(mask.sum()))
    one = np.eye(k)
    here = mask[:, 1:] & mask[:, :-1]
    seen, gradients = np.zeros((k, k)), []
    np.add.at(seen, (gold[:, :-1][here], gold[:, 1:][here]), 1)
    for _ in range(ROUNDS):
        emission = summed(owner, weights[flat], len(index))[ids]
        post, _, pairs = forward_backward(emission, mask, np.exp(trans))
        gap = ((one[gold] - post) * mask[..., None]).reshape(-1, k)
        by_word = np.stack([np.bincount(ids.ravel(), gap[:, y], len(index)) for y in range(k)], axis=1)
        grad = summed(flat, by_word[owner], 1 << SLOTS) / n - PENALTY * weights / n
        grad_t = (seen - pairs) / n - PENALTY * trans
        gradients.append(float(np.sqrt((grad**2).sum() + (grad_t**2).sum())))
        past += grad**2
        past_t += grad_t**2
        weights += STEP * grad / np.sqrt(past)
        trans += 0.2 * grad_t / np.sqrt(past_t)
    return Model(labels, weights.astype(np.float32), trans, lexicon, gradients)


class Labeller:
    """Label probabilities of the words of a batch of texts."""

    def __init__(self, model: Model):
        self.model, self.k = model, len(model.labels)
        self.step = np.exp(model.transitions)
        self.reset()

    def reset(self) -> None:
        self.known: dict[str, int] = {}
        self.rows = np.zeros((0, self.k), np.float64)

    def learn(self, words: list[str]) -> None:
        """Emission factors of new words; -1 for words without a letter."""
        new = [w for w in words if any(c.isalpha() for c in w)]
        self.known.update(dict.fromkeys(words, -1))
        if new:
            owner, slots = features(new, self.model.lexicon)
            e = summed(owner, self.model.weights[slots], len(new))
            self.known.update(zip(new, range(len(self.rows), len(self.rows) + len(new)), strict=True))
            self.rows = np.concatenate((self.rows, np.exp(e - e.max(axis=1, keepdims=True))))

    def words(self, batch: list[str]) -> tuple[np.ndarray, np.ndarray, list[list[str]]]:
        """Marginals of all words in order, the number of words of each text, and the words."""
        found = [WORD.findall(t.lower()) for t in batch]
        if len(self.known) > KEPT:
            self.reset()
        if new := set().union(*found) - self.known.keys():
            self.learn(sorted(new))
        known = self.known
        ids = [[k for w in x if (k := known[w]) >= 0] for x in found]
        counts = np.fromiter(map(len, ids), np.int64, len(ids))
        flat = np.fromiter((k for x in ids for k in x), np.int64, int(counts.sum()))
        return self.marginals(self.rows[flat], counts), counts, found

    def marginals(self, e: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Forward-backward over texts that lie one after another in e (factors, words x labels)."""
        n, k, step = len(e), self.k, self.step
        if not n:
            return e
        parts = -(-counts // SEGMENT)
        text = np.repeat(np.arange(len(counts)), parts)
        first = np.cumsum(parts) - parts
        number = np.arange(len(text)) - first[text]
        start = (np.cumsum(counts) - counts)[text] + number * SEGMENT
        length = np.minimum(SEGMENT, counts[text] - number * SEGMENT)
        long = int(length.max())
        at = np.minimum(start[:, None] + np.arange(long), n - 1)
        on = np.arange(long) < length[:, None]
        f = np.where(on[..., None], e[at], 1.0)
        # Transfer through each segment, from the state before it: rows are the states before.
        through = np.broadcast_to(np.eye(k), (len(text), k, k)).copy()
        for i in range(long):
            m = (through @ step) * f[:, i, None, :]
            m /= m.max(axis=(1, 2), keepdims=True)
            through = np.where(on[:, i, None, None], m, through)
        before, after = np.empty((len(text), k)), np.ones((len(text), k))
        uniform = np.linalg.solve(step.T, np.ones(k)) if np.linalg.matrix_rank(step) == k else np.ones(k)
        before[number == 0] = uniform  # one step from it gives every first label the same weight
        for i in range(1, int(number.max()) + 1):
            own = np.flatnonzero(number == i)
            v = np.einsum("sa,sab->sb", before[own - 1], through[own - 1])
            before[own] = v / np.abs(v).max(axis=1, keepdims=True)
        for i in range(int(number.max()) - 1, -1, -1):
            own = np.flatnonzero((number == i) & (np.append(text[1:], -1) == text))
            v = np.einsum("sab,sb->sa", through[own + 1], after[own + 1])
            after[own] = v / v.max(axis=1, keepdims=True)
        alpha = np.empty((len(text), long, k))
        a = before
        for i in range(long):
            v = (a @ step) * f[:, i]
            v /= v.max(axis=1, keepdims=True)
            a = np.where(on[:, i, None], v, a)
            alpha[:, i] = a
        b = after
        for i in range(long - 1, -1, -1):
            alpha[:, i] *= b
            v = (f[:, i] * b) @ step.T
            v /= v.max(axis=1, keepdims=True)
            b = np.where(on[:, i, None], v, b)
        post = np.maximum(alpha[on], 0)
        return post / post.sum(axis=1, keepdims=True)


def fit(docs: DataFrame, per_label: int = PER_LABEL) -> Model:
    """A model from labelled docs (text, lang)."""
    model = train(sample(docs, per_label))
    released()
    return model


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """docs (doc_id, text) with lang_pred, score and n_words."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        labeller = Labeller(shipped.value)
        for whole in batches:
            for batch in chunks(whole, 1, 1 << 20):
                body = texts(batch.column(1))
                if not labeller.k:
                    names, scores, counts = [UNKNOWN] * len(body), [0.0] * len(body), [0] * len(body)
                else:
                    post, counts, _ = labeller.words(body)
                    sums = np.zeros((len(body), labeller.k))
                    full = np.flatnonzero(counts)
                    if len(full):
                        sums[full] = np.add.reduceat(post, (np.cumsum(counts) - counts)[full], axis=0) / counts[full, None]
                    best = sums.argmax(axis=1)
                    names = [labeller.model.labels[b] if n else UNKNOWN for b, n in zip(best, counts, strict=True)]
                    scores = np.clip(sums.max(axis=1), 0.0, 1.0)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(counts, pa.int64())], ["doc_id", "lang_pred", "score", "n_words"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(returning(run), "doc_id long, lang_pred string, score double, n_words long")


def label_words(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, words array<struct<word, lang, p>>) of each text: the labels of code-switched words."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)
    kind = pa.list_(pa.struct([("word", pa.string()), ("lang", pa.string()), ("p", pa.float64())]))

    def run(batches):
        labeller = Labeller(shipped.value)
        for whole in batches:
            for batch in chunks(whole, 1, 1 << 20):
                post, counts, found = labeller.words(texts(batch.column(1)))
                best, p, at, out = post.argmax(axis=1) if len(post) else [], post.max(axis=1) if len(post) else [], 0, []
                for n, words in zip(counts, found, strict=True):
                    kept = [w for w in words if labeller.known[w] >= 0]
                    out.append([{"word": w, "lang": labeller.model.labels[best[at + i]], "p": float(p[at + i])} for i, w in enumerate(kept)])
                    at += int(n)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, kind)], ["doc_id", "words"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, words array<struct<word:string,lang:string,p:double>>")


def held_out() -> F.Column:
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(4)) == 2


def language_report(docs: DataFrame) -> DataFrame:
    """What op4 returns: doc_id, held_out, lang_pred, score. Rows that are held out are never learned from."""
    model = fit(docs.filter(~held_out()).select("text", "lang"))
    return predict(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


def keep_confident(docs: DataFrame, model: Model | None = None, least: float = 0.5) -> DataFrame:
    """docs without those that have no letter, or whose likeliest language has less than `least` of their words; columns as they came.

    Without a labelled row there is no model, and all rows stay.
    """
    model = model or fit(docs.select("text", "lang"))
    if not model.labels:
        return docs
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        labeller = Labeller(shipped.value)
        for whole in batches:
            at = whole.schema.get_field_index("text")
            for batch in chunks(whole, at, 1 << 20):
                post, counts, _ = labeller.words(texts(batch.column(at)))
                full = np.flatnonzero(counts)
                if len(full):
                    top = (np.add.reduceat(post, (np.cumsum(counts) - counts)[full], axis=0) / counts[full, None]).max(axis=1)
                    yield batch.take(pa.array(full[top >= least]))

    return docs.mapInArrow(returning(run), docs.schema)
