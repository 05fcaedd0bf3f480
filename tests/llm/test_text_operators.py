"""Each operator against brute force, the reference library or held-out rows, with nulls, ties, repeats, long and empty texts."""

import hashlib
import random
import re
import time
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from skyjoin.llm import crf_language, lexicon_automata, line_dedup, minhash, pfair_mix, piece_transducer, prefix_join, shingles, surrogates, token_counts, transport_stream
from skyjoin.llm.components import components
from skyjoin.llm.queries import vocabulary

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
LINE = "this line is shared by several documents"
WORDS = [f"w{k}" for k in range(400)]


def rows():
    rng = random.Random(5)
    base = [" ".join(rng.choice(WORDS) for _ in range(120)) for _ in range(6)]
    out = [(1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "One two THREE four"), (6, "one two three four"), (7, "日本語 テキスト 🎉 é"), (8, "x" * 5000), (9, base[0] + "\n" + LINE)]
    out += [(10, base[0] + " tail"), (11, base[1] + "\n " + LINE.upper() + "\t\n" + LINE), (12, base[1] + "\n" + LINE), (13, base[1]), (14, base[2]), (15, base[2]), (15, base[2]), (16, base[3] + "\n\n"), (20, " ".join(base) * 3)]
    for k in range(12):  # a chain of near copies
        w = base[4].split()
        w[k * 9 : k * 9 + 4] = [f"n{k}{j}" for j in range(4)]
        out.append((30 + k, " ".join(w)))
    out.append((None, base[3]))
    return [(i, t, ("en", "de")[k % 2] if k % 5 else None, ("a", "b", None)[k % 3], len(t or "")) for k, (i, t) in enumerate(out)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def extra(docs):
    """Extra columns whose names clash with outputs and working columns."""
    return clashing(docs)


def clashing(df):
    names = "n_lines ids block N_Dropped slot entities label score n_tokens media digest fingerprint component_id at bucket lang_pred toxic mix_order place"
    return df.withColumns({n: F.lit("x") for n in names.split() if n not in df.columns})


REPORTS = {
    "op1": lambda d: lexicon_automata.toxicity_report(d, d.selectExpr("doc_id", "cast(doc_id % 2 AS int) AS toxic")),
    "op2": lambda d: token_counts.token_counts(d, vocabulary()),
    "op3": transport_stream.media_columns,
    "op4": crf_language.language_report,
    "op5": lambda d: piece_transducer.round_trip(d, vocabulary()),
    "op6": minhash.edited_fingerprints,
    "op7": surrogates.surrogate_report,
    "op8": prefix_join.link_classes,
    "op9": lambda d: line_dedup.dedup_lines(d).select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("t")),
    "op10": lambda d: pfair_mix.mix(d).select("doc_id", F.col("mix_order")),
}


@pytest.mark.parametrize("name", REPORTS)
def test_odd_tables(docs, none, name):
    """Clashing columns, repeated rows, a null id, null, empty and long texts: a row for each row, equal rows alike; empty tables."""
    long = docs.sparkSession.createDataFrame([(77, "the word of it was in a long text " * 30_000, "en", "a", 1), (78, "n" * 200_000, "en", "b", 1)], SCHEMA)
    table = docs.unionByName(long).unionByName(docs.filter("doc_id IN (5, 9, 13)"))
    plain, wide = ([tuple(r) for r in REPORTS[name](t).collect()] for t in (table, clashing(table)))
    assert len(plain) == table.count() and sorted(map(str, plain)) == sorted(map(str, wide))
    ids = [r[0] for r in plain]
    assert ids.count(5) == ids.count(13) == 2 and ids.count(None) == 1 and {77, 78} <= set(ids)
    if name != "op10":  # rows of one id and text are alike
        assert all(len({str(r) for r in plain if r[0] == i}) == 1 for i in (5, 9, 13))
    assert REPORTS[name](none).count() == 0


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if c < "\x80" else c for c in t or ""))


def grams(t):
    w = words(t)
    return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()


# Tokens ------------------------------------------------------------------------------------------------------------------

TEXTS = ["", " ", "  a", "a  b ", "\n\n", "a\tb", "é", "é", "①", "▁x▁ ", "<s></s><unk><0x41>", "\x00a", "日本語テキスト", "𝔘 Ａ１", "x" * 3000, "ab" * 700 + " " * 40, "=-" * 300, "don't STOP... 1234567", "a" + "́" * 40]


def library():
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=vocabulary())


def test_token_counts_equal_the_library(spark, docs, none):
    m, lib = token_counts.merger(vocabulary()), library()
    rng = random.Random(2)
    texts = TEXTS + ["".join(rng.choice("ab ▁\né日x1.,") for _ in range(rng.randint(0, 60))) for _ in range(300)]
    assert m.count(texts) == [len(x) for x in lib.encode(texts)]
    for letters, n in (("etaoin", 5000), ("abcdefghijklmnopqrstuvwxyz", 5000), ("ab", 5000), ("a", 5000)):  # long sequences, by rounds alone
        t = "".join(rng.choice(letters) for _ in range(n))
        assert m.ragged(["▁" + t]).tolist() == [len(lib.encode(t))]
    got = token_counts.token_counts(docs, vocabulary()).collect()
    assert len(got) == docs.count()
    text = {}
    for i, t, *_ in rows():
        text[i] = t or ""
    for r in got:
        assert r.n_tokens == len(lib.encode(text[r.doc_id])) and r.n_bytes == len(text[r.doc_id].encode()) and r.over_limit == (r.n_tokens > 4096)
    assert token_counts.token_counts(none, vocabulary()).count() == 0


def test_transducer_equals_the_library(docs, extra, none):
    t, lib = piece_transducer.transducer(vocabulary()), library()
    rng = random.Random(3)
    texts = TEXTS + ["".join(rng.choice("abehtn ▁\né日x1.,") for _ in range(rng.randint(0, 60))) for _ in range(300)]
    want = lib.encode(texts)
    assert t.encode(texts) == want
    assert [t.decode(x) for x in want] == [lib.decode(x) for x in want]
    got = piece_transducer.encode_texts(extra, vocabulary())
    assert got.columns.count("ids") == 1 and got.count() == extra.count()
    assert all(r.lossless for r in piece_transducer.round_trip(docs, vocabulary()).collect())
    back = piece_transducer.decode_texts(got, vocabulary()).filter("text IS NOT NULL AND decoded <> text")
    assert back.count() == 0 and piece_transducer.round_trip(none, vocabulary()).count() == 0


def spelled_paths(text, pieces, byte_ids, byte, pair):
    """All segmentations of a text with their weights: pieces, or bytes of characters that are none."""
    if not text:
        yield 0.0, []
    for k in range(1, len(text) + 1):
        for weight, rest in spelled_paths(text[k:], pieces, byte_ids, byte, pair) if text[:k] in pieces else ():
            number = pieces[text[:k]][0]
            yield weight + pieces[text[:k]][1] + (pair(number, rest[0]) if rest and rest[0] < 100 else 0.0), [number, *rest]
    if text and text[0] not in pieces:
        own = [byte_ids[b] for b in text[0].encode()]
        for weight, rest in spelled_paths(text[1:], pieces, byte_ids, byte, pair):
            yield weight + byte * len(own), own + rest


class Pairs:
    """A pair acceptor with unequal weights, some infinite."""

    def one(self, a, b):
        return [0.0, 0.5, 2.0, float("inf")][(7 * a + 3 * b) % 4]

    def weights(self, a, b):
        return np.array([self.one(x, y) if x >= 0 and y >= 0 else 0.0 for x, y in zip(a.tolist(), b.tolist(), strict=True)])


@pytest.mark.parametrize("pairs", [None, Pairs()])
def test_shortest_path_against_all_paths(pairs):
    """Small vocabularies with unequal weights: the least weight of all paths, of parts together and one by one."""
    rng = random.Random(6)
    byte_ids, text = list(range(100, 356)), []
    for _ in range(25):
        pieces = {p: (i, rng.choice([0.25, 0.5, 1.0, 1.75, 3.0]) + i / 1024) for i, p in enumerate(sorted({"".join(rng.choice("abc") for _ in range(rng.randint(1, 4))) for _ in range(9)}))}
        t = piece_transducer.Transducer(pieces, byte_ids, 356, pairs, byte=4.0)
        texts = ["".join(rng.choice("abcé") for _ in range(rng.randint(1, 8))) for _ in range(12)]
        for x, got in zip(texts, t.shortest(texts), strict=True):
            paths = sorted((w, p) for w, p in spelled_paths(x, pieces, byte_ids, 4.0, pairs.one if pairs else lambda a, b: 0.0) if w < float("inf"))
            want = [p for w, p in paths if w <= paths[0][0] + 1e-9] if paths else [[byte_ids[b] for b in x.encode()]]
            assert got in want and t.shortest_one(x) in want
            text.append(len(paths))
    assert max(text) > 5


def test_pair_acceptor_is_what_merging_gives():
    t = piece_transducer.transducer(vocabulary())
    rng, ids = np.random.default_rng(3), np.flatnonzero(t.pairs.whole)
    a, b = rng.choice(ids, 6000), rng.choice(ids, 6000)
    words = [p.encode("utf-8", "ignore").decode() for p in t.pieces if p.isascii()]
    extra = [(t.pieces[p[:k]][0], t.pieces[p[k:]][0]) for p in words for k in range(1, len(p)) if p[:k] in t.pieces and p[k:] in t.pieces][:4000]
    a, b = np.append(a, [x for x, _ in extra]), np.append(b, [y for _, y in extra])
    assert t.pairs.weights(a, b).tolist() == [t.pairs.one(x, y) for x, y in zip(a.tolist(), b.tolist(), strict=True)]


# Media ------------------------------------------------------------------------------------------------------------------


def test_transport_stream_round_trip_and_damage():
    rng = random.Random(4)
    for n in (0, 1, 170, 175, 176, 183, 184, 575, 576, 5760, 5761, 60000):
        data = transport_stream.padded(rng.randbytes(n))
        media = transport_stream.write_stream(data)
        s = transport_stream.read_stream(media)
        assert s.payload() == data and len(data) % 576 == 0 and data and len(media) % 188 == 0
        assert s.counter_errors == s.table_errors == s.duplicates == s.skipped == 0 and s.streams == {transport_stream.DATA_PID: 6}
        assert [u.pts for u in s.units] == [k * transport_stream.TICKS for k in range(len(s.units))] and s.index()[0][1] == 0
    packets = [media[k : k + 188] for k in range(0, len(media), 188)]
    lost = transport_stream.read_stream(b"".join(packets[:7] + packets[8:]))
    assert lost.counter_errors == 1 and sum(u.damaged for u in lost.units) == 1
    twice = transport_stream.read_stream(b"".join(packets[:7] + packets[6:]))
    assert twice.duplicates == 1 and twice.payload() == data
    assert transport_stream.read_stream(b"junk" + media).payload() == data
    broken = bytearray(media)
    broken[20] ^= 1
    assert transport_stream.read_stream(bytes(broken)).table_errors == 1
    assert transport_stream.read_stream(b"").units == [] and transport_stream.read_stream(b"\x47" * 50).packets == 0


def test_media_columns(docs, none):
    text = {i: (t or "").encode() for i, t, *_ in rows()}
    seen = {}
    for r in transport_stream.media_columns(docs).collect():
        p = transport_stream.padded(text[r.doc_id])
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(text[r.doc_id]), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:]))
        assert seen.setdefault(text[r.doc_id], (r.media_sha256, r.feature)) == (r.media_sha256, r.feature)
    assert transport_stream.media_columns(none).count() == 0


def test_stored_media_and_access_units(spark):
    text = "long text " * 50_000  # 500 KB: 87 units, 11 random-access points
    stored = transport_stream.stored_media(spark.createDataFrame([(1, text), (2, None)], "doc_id long, text string"))
    rows = {r.doc_id: r for r in stored.collect()}
    assert rows[1].media == transport_stream.write_stream(transport_stream.padded(text.encode())) and rows[1].payload.startswith(text.encode())
    points = [tuple(p) for p in rows[1].access_points]
    assert points == transport_stream.read_stream(rows[1].media).index() and len(points) == 11 and len(rows[2].access_points) == 1
    assert [p[1:] for p in points] == [(k * 8 * transport_stream.TICKS, k * 8 * transport_stream.UNIT) for k in range(11)]
    units = sorted(transport_stream.access_units(stored).filter("doc_id = 1").collect(), key=lambda u: u.unit)
    assert [u.pts for u in units] == [k * transport_stream.TICKS for k in range(87)] and sum(u.n_bytes for u in units) == len(rows[1].payload)
    assert [(u.packet, u.pts) for u in units if u.random_access] == [p[:2] for p in points] and not any(u.damaged for u in units)
    report = transport_stream.media_columns(spark.createDataFrame([(1, text)], "doc_id long, text string")).first()
    assert report.random_access_points == 11 and [tuple(p) for p in report.access_points] == points


# Lines ------------------------------------------------------------------------------------------------------------------


def line_brute(data):
    holders = {}
    for i, t, *_ in data:
        for x in (t or "").split("\n"):
            k = "".join(c.lower() if c < "\x80" else c for c in x.strip(" \t\n\x0b\x0c\r"))
            if len(k) >= 20:
                holders.setdefault(k, set()).add(-(2**63) if i is None else i)
    out = []
    for i, t, *_ in data:
        keep = []
        for x in (t or "").split("\n"):
            k = "".join(c.lower() if c < "\x80" else c for c in x.strip(" \t\n\x0b\x0c\r"))
            own = holders.get(k, set())
            if not (len(own) >= 3 and (-(2**63) if i is None else i) != max(own)):
                keep.append(x)
        out.append((i, len((t or "").split("\n")), len((t or "").split("\n")) - len(keep), hashlib.sha256("\n".join(keep).encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("bits", [None, 6])
def test_line_dedup(docs, extra, none, bits):
    """A filter of 64 bits makes every line a suspect: the result is the same."""
    got = line_dedup.dedup_lines(docs.select("doc_id", "text"), bits=bits).select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256)).collect()
    assert sorted(map(tuple, got), key=str) == line_brute(rows())
    if bits is None:
        wide = line_dedup.dedup_lines(extra)
        assert wide.schema["n_lines"].dataType.simpleString() == "bigint" and wide.count() == extra.count()
        assert line_dedup.dedup_lines(none).count() == 0


# Near-duplicates ----------------------------------------------------------------------------------------------------------


def class_brute(data):
    sets = {}
    for i, t, *_ in data:
        if i is not None:
            sets.setdefault(i, []).append(grams(t))
    label = {i: i for i in sets}

    def find(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in sets:
        for j in sets:
            if j < i and any(x and y and 100 * len(x & y) >= 75 * len(x | y) for x in sets[i] for y in sets[j]):
                a, b = find(i), find(j)
                label[max(a, b)] = min(a, b)
    return sorted(((i, len(grams(t)), None if i is None else find(i)) for i, t, *_ in data), key=str)


def test_prefix_tree_join(docs, none, monkeypatch):
    for small, chunk, pivots in ((16, 512, 4), (2, 3, 1), (1, 5, 2)):  # the others: stars for almost all shingles, blocks in cuts
        monkeypatch.setattr(prefix_join, "SMALL", small)
        monkeypatch.setattr(prefix_join, "CHUNK", chunk)
        monkeypatch.setattr(prefix_join, "PIVOTS", pivots)
        got = prefix_join.link_classes(docs.select("doc_id", "text"))
        assert sorted(map(tuple, got.collect()), key=str) == class_brute(rows())
    assert prefix_join.link_classes(none).count() == 0
    kept = prefix_join.first_of_each_class(docs)
    heads = {c for _, _, c in class_brute(rows()) if c is not None}
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect() if r.doc_id is not None} == heads


def test_prefix_join_in_cuts_against_brute_force(spark, monkeypatch):
    """Groups of near copies around shared passages, with most shingles frequent and blocks cut: classes and sets as by brute force."""
    rng = random.Random(12)
    monkeypatch.setattr(prefix_join, "SMALL", 3)
    monkeypatch.setattr(prefix_join, "CHUNK", 6)
    common = " ".join(rng.choice(WORDS) for _ in range(30))
    data, i = [], 0
    for g in range(6):
        base = (common + " " + " ".join(rng.choice(WORDS) for _ in range(rng.choice((25, 50))))).split()
        for _ in range(14):
            w = list(base)
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = f"x{rng.randrange(900)}"
            data.append((i := i + 1, " ".join(w), "en", "a", 0))
    got = prefix_join.link_classes(spark.createDataFrame(data, SCHEMA).repartition(5).select("doc_id", "text"))
    assert sorted(map(tuple, got.collect()), key=str) == class_brute(data)


def test_near_copies_meet_in_proportion(spark, monkeypatch):
    """Twice the near copies: about twice the rows that enter the trees, not four times."""
    rng, met = random.Random(13), []
    base = [rng.choice(WORDS) for _ in range(60)]
    total = spark.sparkContext.accumulator(0)

    def counting(make):
        def made(percent):
            run = make(percent)

            def counted(rows):
                total.add(len(rows))
                return run(rows)

            return counted

        return made

    for name in ("_join", "_meet"):
        monkeypatch.setattr(prefix_join, name, counting(getattr(prefix_join, name)))
    monkeypatch.setattr(prefix_join, "CHUNK", 64)
    for n in (1500, 3000):
        data = []
        for i in range(n):
            w = list(base)
            w[rng.randrange(60)] = f"y{i}"
            data.append((i, " ".join(w)))
        before = total.value
        got = prefix_join.link_classes(spark.createDataFrame(data, "doc_id long, text string").repartition(8))
        assert {r.component_id for r in got.collect()} == {0}
        met.append(total.value - before)
    assert met[0] < 4 * 1500 and met[1] < 2.5 * met[0]


def test_prefix_tree_against_all_pairs():
    rng = random.Random(9)
    for _ in range(150):
        pool = [np.array(rng.sample(range(60), rng.randint(1, 25)), np.uint64) for _ in range(3)]
        sets = []
        for _ in range(rng.randint(1, 25)):
            s = set(rng.choice(pool).tolist())
            for _ in range(rng.randint(0, 5)):
                s.discard(rng.choice(sorted(s))) if rng.random() < 0.5 and len(s) > 1 else s.add(rng.randrange(90))
            sets.append(np.array(sorted(s), np.uint64))
        got = prefix_join.linked_classes(sets).tolist()
        label = list(range(len(sets)))
        for i in range(len(sets)):
            for j in range(i):
                a, b = set(sets[i].tolist()), set(sets[j].tolist())
                if 100 * len(a & b) >= 75 * len(a | b):
                    x, y = label[i], label[j]
                    label = [min(x, y) if v in (x, y) else v for v in label]
        assert [got.index(v) for v in got] == [label.index(v) for v in label]


def test_prefix_holds_every_link():
    """Any two sets at the threshold share a shingle of both prefixes, whatever the global order."""
    rng = random.Random(1)
    for _ in range(300):
        a = set(rng.sample(range(1000), rng.randint(1, 40)))
        b = set(a)
        for _ in range(rng.randint(0, 12)):
            b.discard(rng.choice(sorted(b))) if rng.random() < 0.5 and len(b) > 1 else b.add(rng.randrange(1000))
        if 100 * len(a & b) >= 75 * len(a | b):
            p = [set(sorted(x)[: prefix_join.prefix_length(len(x))]) for x in (a, b)]
            assert p[0] & p[1]


def test_shingles_of_pieces(monkeypatch):
    text = ("alpha beta\tgamma " * 3000).encode()
    want = shingles.word_hashes(text)
    monkeypatch.setattr(shingles, "PIECE", 1000)
    assert (shingles.word_hashes(text) == want).all()
    assert [len(s) for s in shingles.shingle_sets([text, b"", b"A b", b"a B"])] == [3, 0, 1, 1]


def test_components(spark):
    rng = random.Random(6)
    edges = [(rng.randrange(80), rng.randrange(80)) for _ in range(50)] + [(200, k) for k in range(201, 240)] + [(k, k + 1) for k in range(300, 330)] + [(5, 5)]
    label = {}
    for a, b in edges:
        if a != b:
            x, y = label.get(a, a), label.get(b, b)
            label.setdefault(a, a), label.setdefault(b, b)
            label = {k: min(x, y) if v in (x, y) else v for k, v in label.items()}
    got = dict(map(tuple, components(spark.createDataFrame(edges, "a long, b long")).collect()))
    assert got == label
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


# Fingerprints -------------------------------------------------------------------------------------------------------------


def test_minhash(spark, none):
    rng = random.Random(8)
    data = [(k * k, " ".join(rng.choice(WORDS) for _ in range(rng.choice((3, 8, 40, 300))))) for k in range(40)] + [(5000, ""), (5001, None), (5002, " \n"), (5003, "é" * 7), (5004, "é" * 7)]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    got = {r.doc_id: r for r in minhash.edited_fingerprints(df).collect()}
    order = sorted(data, reverse=True, key=lambda x: x[0])
    errors, same = [], {}
    for k, (i, t) in enumerate(order):
        t, nxt = t or "", order[(k + 1) % len(order)][1] or ""
        half = len(t) // 2
        edited = t[: len(t) - half] + nxt[:half]
        r = got[i]
        assert r.n_chars == len(t) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert same.setdefault(t, r.fingerprint) == r.fingerprint and 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
        a, b = grams(t), grams(edited)
        if a and b:
            errors.append(r.near_edited - len(a & b) / len(a | b))
    assert len(got) == len(data) and abs(np.mean(errors)) < 0.05 and np.sqrt(np.mean(np.square(errors))) < 0.08
    assert minhash.edited_fingerprints(none).count() == 0
    assert all(sorted(w) == list(range(minhash.BINS)) for w in minhash.walks())
    plan = minhash.edited_fingerprints(df)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


def test_fingerprint_by_hand(spark):
    """The fingerprint itself: bins, densification and packing in plain Python."""
    import xxhash

    def hashed(words):
        h = 42
        for w in words:
            h = xxhash.xxh64(w.encode(), seed=h).intdigest()
        return h - (1 << 64) if h >> 63 else h

    def by_hand(text):
        w = re.findall(r"[^\x20\x09-\x0D]+", text.lower())
        if not w:
            return "-"
        least = {}
        for h in {hashed(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {hashed(w)}:
            k = (h >> 57) + 64
            least[k] = min(h, least.get(k, h))
        full = [least[i] if i in least else next(least[k] for k in minhash.walks()[i] if k in least) for i in range(128)]
        return "".join(f"{h & 255:02x}" for h in full)

    rng = random.Random(4)
    texts = [" ".join(rng.choice(WORDS) for _ in range(n)) for n in (1, 3, 5, 6, 20, 130, 400, 3000)] + ["", "  ", "One TWO three Four five Six"]
    rows_ = spark.createDataFrame([(t,) for t in texts], "t string").select("t", minhash.fingerprint(F.col("t"))).collect()
    assert [f for _, f in rows_] == [by_hand(t) for t, _ in rows_]
    a, b = by_hand(texts[5]), by_hand(texts[6])
    same = sum(a[k : k + 2] == b[k : k + 2] for k in range(0, 256, 2)) / 128
    got = spark.createDataFrame([(a, b)], "a string, b string").select(minhash.likeness(F.col("a"), F.col("b"))).first()[0]
    assert abs(got - max(0.0, (same - 1 / 256) / (1 - 1 / 256))) < 1e-12


def test_next_lower(spark):
    for ids in ([7], [1, 2, 3], [k * k * k for k in range(9000)], [-5, 0, 2**62, -(2**62)]):
        got = dict(map(tuple, minhash.next_lower(spark.createDataFrame([(i,) for i in ids], "id long")).collect()))
        order = sorted(ids, reverse=True)
        assert got == {i: order[(k + 1) % len(order)] for k, i in enumerate(order)}


# Mixing -------------------------------------------------------------------------------------------------------------------


def test_pfair_mix(spark, docs, extra, none):
    counts = {"a": 900, "b": 300, "c": 40, None: 7}
    data = [(i, s) for i, s in enumerate(s for s, n in counts.items() for _ in range(n))]
    df = spark.createDataFrame(data, "doc_id long, source string").repartition(4)
    weights = spark.createDataFrame([("a", 0.5), ("b", 0.3), ("c", 0.15), (None, 0.05)], "source string, weight double")
    got = sorted(pfair_mix.mix(df, weights, block=4, period=100).collect(), key=lambda r: r.mix_order)
    assert len(got) == len(data) and len({r.mix_order for r in got}) == len(data) and len({r.doc_id for r in got}) == len(data)
    blocks = {}
    for r in got:
        assert r.release <= r.slot < r.deadline
        blocks.setdefault(r.source, {})[r.block] = r.slot
    share = {r.source: r.share for r in got}
    period = got[0].period
    assert period > 300 and all(abs(share[s] / period - w) < 1 / period for s, w in (("a", 0.5), ("b", 0.3), ("c", 0.15), (None, 0.05)))
    for s, own in blocks.items():
        slots = sorted(own.values())
        assert list(own) == sorted(own) and slots == [own[k] for k in sorted(own)]
        for t in range(slots[-1] + 1):  # less than one block off the target at every time
            assert abs(sum(x < t for x in slots) - t * share[s] / period) < 1
    exact = spark.createDataFrame([("a", 0.7131), ("b", 0.2867), ("c", 0.0002), (None, 0.0)], "source string, weight double")
    slots = {}
    for r in pfair_mix.mix(df.union(df.selectExpr("doc_id + 5000", "source")), exact, block=1).collect():
        slots.setdefault(r.source, []).append(r.slot)
    ends = {s: max(x) for s, x in slots.items()}
    for s, w in (("a", 0.7131), ("b", 0.2867)):  # the given weights: a block of lag, and less than one of rounding
        own = np.sort(slots[s])
        for t in range(0, min(ends["a"], ends["b"]), 7):
            assert abs(np.searchsorted(own, t) - t * w) < 2
    assert len(slots["c"]) == 80 and min(slots[None]) > max(ends[s] for s in "abc")
    wide = pfair_mix.mix(extra)
    assert wide.count() == extra.count() and wide.columns.count("slot") == 1
    assert pfair_mix.mixed(docs).columns == docs.columns and pfair_mix.mixed(docs).count() == docs.count()
    assert pfair_mix.mix(none).count() == 0
    assert not re.search("Python|Arrow|Pandas", pfair_mix.mix(df)._jdf.queryExecution().executedPlan().toString())


# Language -----------------------------------------------------------------------------------------------------------------


def test_forward_backward_in_segments():
    rng = np.random.default_rng(1)
    model = crf_language.Model(["a", "b", "c"], np.zeros((1 << crf_language.SLOTS, 3), np.float32), rng.normal(size=(3, 3)), {})
    lab = crf_language.Labeller(model)
    counts = np.array([1, 0, 63, 64, 65, 200])
    e = rng.random((counts.sum(), 3)) + 0.01
    got, at = lab.marginals(e, counts), 0
    for n in counts:
        if n:
            want, _, _ = crf_language.forward_backward(np.log(e[at : at + n])[None], np.ones((1, n), bool), lab.step)
            assert np.abs(got[at : at + n] - want[0]).max() < 1e-9
        at += n
    e = np.log(e[:4])  # against all label sequences
    total = np.zeros((4, 3))
    for a in np.ndindex(3, 3, 3, 3):
        p = np.exp(sum(e[i, a[i]] for i in range(4)) + sum(model.transitions[a[i], a[i + 1]] for i in range(3)))
        for i in range(4):
            total[i, a[i]] += p
    want, _, _ = crf_language.forward_backward(e[None], np.ones((1, 4), bool), lab.step)
    assert np.abs(total / total.sum(axis=1, keepdims=True) - want[0]).max() < 1e-9


def test_language(spark, sf, docs, extra, none):
    table = spark.read.parquet(f"{sf}/documents.parquet")
    out = crf_language.language_report(table).join(table.select("doc_id", "lang"), "doc_id").filter("held_out").collect()
    assert len(out) > 20 and sum(r.lang == r.lang_pred for r in out) / len(out) > 0.95
    got = {r.doc_id: r for r in crf_language.language_report(docs).collect()}
    assert [got[i].lang_pred for i in (1, 2, 3)] == ["und"] * 3 and all(0 <= r.score <= 1 for r in got.values())
    assert crf_language.language_report(none).count() == 0
    assert {r.lang_pred for r in crf_language.language_report(docs.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}
    kept = crf_language.keep_confident(extra, least=0.0)
    assert kept.columns == extra.columns and {1, 2, 3}.isdisjoint({r.doc_id for r in kept.collect()})
    model = crf_language.fit(table)
    mixed = spark.createDataFrame([(1, "the of and was that " * 6 + "der die und nicht einer " * 6)], "doc_id long, text string")
    labels = [w["lang"] for w in crf_language.label_words(mixed, model).first().words]
    assert set(labels[:24]) == {"en"} and set(labels[-24:]) == {"de"}


def test_copies_count_once_in_the_sample(spark):
    texts = [f"text number {k} of the table" for k in range(40)]
    df = spark.createDataFrame([(t, "en") for t in texts for _ in range(50)], "text string, lang string").repartition(4)
    got = crf_language.sample(df, per_label=30)
    assert len(got) == len(set(got)) == 30 and {k for _, k in got} == {"en"}


def test_no_language_is_lost_to_copies(spark):
    """One English text 20,000 times beside 100 German ones, and tables of copies alone."""
    german = [("der die und nicht einer %d" % k, "de") for k in range(100)]
    for text in ("the of and was that", "this is it", "a word in the text"):
        df = spark.range(20_000).select(F.lit(text).alias("text"), F.lit("en").alias("lang"))
        got = crf_language.sample(df.unionByName(spark.createDataFrame(german, "text string, lang string")))
        assert sum(k == "en" for _, k in got) == 1 and sum(k == "de" for _, k in got) == 100
    many = spark.range(3000).selectExpr("concat('text number ', id) AS text", "concat('l', id % 3) AS lang")
    got = crf_language.sample(many, per_label=50)
    assert len(got) == 150 and all(sum(k == f"l{j}" for _, k in got) == 50 for j in range(3))


def test_training_converges(spark):
    table = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    lengths = crf_language.fit(table).gradients
    assert len(lengths) == crf_language.ROUNDS and lengths[-1] < 0.1 * lengths[0]


# Toxicity -----------------------------------------------------------------------------------------------------------------


def edits(a, b):
    p = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        q = [i]
        for j, y in enumerate(b, 1):
            q.append(min(p[j] + 1, q[-1] + 1, p[j - 1] + (x != y)))
        p = q
    return p[-1]


def test_automaton_against_edit_distance():
    rng = random.Random(1)
    for _ in range(30):
        terms = list({"".join(rng.choice("abc") for _ in range(rng.randint(1, 10))) + ("*" if rng.random() < 0.2 else "") for _ in range(8)})
        auto = lexicon_automata.TrieAutomaton(terms)
        for _ in range(150):
            w = "".join(rng.choice("abcd") for _ in range(rng.randint(0, 12)))
            found = [(edits(w, t), i) for i, t in enumerate(terms) if not t.endswith("*") and edits(w, t) <= lexicon_automata.most_edits(t)]
            found += [(0, i) for i, t in enumerate(terms) if t.endswith("*") and w.startswith(t[:-1])]
            got = auto.match(w)
            assert (got and got[0]) == (min(found)[0] if found else None) and (got is None or got in found)


def test_toxicity(spark, docs, none):
    rng = random.Random(3)
    bad = ["grobnik", "zlotvarn", "mirbuk"]
    data, labels = [], []
    for i in range(240):
        w = [rng.choice(WORDS) for _ in range(60)]
        toxic = i % 4 == 0
        if toxic:
            for _ in range(4):
                w[rng.randrange(60)] = rng.choice(bad)
        data.append((i, " ".join(w)))
        labels.append((i, int(toxic)))
    extra_rows = [(1000, " ".join([*WORDS[:20], "grobnlk", "you", "zl0tvarn", *WORDS[20:40]])), (1001, "w1 w2 said 'grobnik' w3"), (1002, "grobnik you grobnik"), (1003, None), (1004, "")]
    df = spark.createDataFrame(data + extra_rows, "doc_id long, text string")
    lab = spark.createDataFrame([*labels, (None, 1), (7, None)], "doc_id long, toxic int")
    out = {r.doc_id: r for r in lexicon_automata.toxicity_report(df, lab).collect()}
    assert len(out) == len(data) + 5 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.7) for r in out.values())
    held = [i for i in range(240) if out[i].held_out]
    assert held and all(out[i].held_out == (zlib.crc32(str(i).encode()) % 3 == 1) for i in range(240))
    assert sum(out[i].predicted == (i % 4 == 0) for i in held) / len(held) > 0.97
    assert out[1000].n_fuzzy == 1 and out[1000].n_hits == 2  # a sign read as its letter is no edit
    assert out[1001].n_quoted == 1 and out[1001].score < out[1002].score and out[1003].score == out[1004].score < 0.5
    assert lexicon_automata.toxicity_report(none, lab).count() == 0
    assert lexicon_automata.toxicity_report(docs, lab.limit(0)).count() == docs.count()


def test_toxicity_recall_by_language(spark):
    """A language with a small part of the corpus gets terms too: held-out rows of sf0.1."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{n}.parquet") for n in ("documents", "labels"))
    scored = lexicon_automata.toxicity_report(docs, labels).filter("held_out").join(labels, "doc_id").join(docs.select("doc_id", "lang"), "doc_id")
    toxic = {r.lang: (r.found, r.n) for r in scored.filter("toxic = 1").groupBy("lang").agg(F.sum("predicted").alias("found"), F.count("*").alias("n")).collect()}
    assert len(toxic) == 4 and all(found >= 0.85 * n for found, n in toxic.values()), toxic
    assert scored.filter("toxic = 0").agg(F.avg("predicted")).first()[0] < 0.01


def test_misspelled_words_of_a_stem():
    rng = random.Random(4)
    rows = [(" ".join([*rng.choices(WORDS, k=40), *([rng.choice(["krelmota", "krelmoten", "krelmotig"])] if y else [])]), y) for y in [0] * 200 + [1] * 60]
    scorer = lexicon_automata.Scorer(lexicon_automata.train(rows))
    assert any(t.endswith("*") and "krelmoten".startswith(t[:-1]) for t in scorer.model.terms)
    for word, edits_ in (("krelmoten", 0), ("krelmotung", 0), ("krxlmoten", 1), ("kelmotig", 1), ("krellmoota", 2)):
        found = scorer.word(word)
        assert found is not None and found[0] == edits_, word
    assert scorer.word("karlmuht") is None


# Personal data --------------------------------------------------------------------------------------------------------------


def test_surrogates(docs, extra, none, spark):
    s = surrogates.Surrogates(b"k")
    text = 'Mail a.b+c@mail7.example.com, +1 (017) 555-7713 or 4111 1111 1111 1111! 169.122.221.182 10.0.0.7 token = "2abc3ff2dead" Mrs Anna Smith, г-н Иван Петров; 123-45-6789 DE89 3704 0044 0532 0130 00.'
    new, found = s.apply(text)
    kinds = [k for _, _, k, _, _ in found]
    assert sorted(kinds) == sorted(["email", "phone", "card", "ip", "ip", "secret", "name", "name", "national", "iban"])
    for _, _, kind, old, image in found:
        assert old not in new and image in new
        if kind != "email":
            assert re.sub(r"\w", "x", image) == re.sub(r"\w", "x", old) or kind in ("ip", "name")
    by = {k: (o, i) for _, _, k, o, i in found}
    digits = re.sub(r"\D", "", by["card"][1])
    assert surrogates.check_digit(digits[:-1]) == int(digits[-1])
    names = [i for _, _, k, _, i in found if k == "name"]
    assert names[0].split()[0] in surrogates.GIVEN["f", "latin"] and names[1].split()[0] in surrogates.GIVEN["m", "cyrillic"]
    assert [i for _, _, k, o, i in found if k == "ip"][1].startswith("10.")
    assert s.apply("plain 3.14 v1.2.3.4.5 2024-01-02 text")[1] == []
    keyed = surrogates.Keyed(b"k")
    for n in (2, 7, 100, 3000):
        assert sorted(keyed.number(i, n, b"t") for i in range(n)) == list(range(n))
    assert len({keyed.text(f"{i:04d}", "t") for i in range(10000)}) == 10000
    assert surrogates.Surrogates(b"other").apply(text)[0] != new
    df = spark.createDataFrame([(1, text), (2, "see a.b+c@mail7.example.com"), (3, None)], "doc_id long, text string")
    out = {r.doc_id: r for r in surrogates.surrogate_report(df).collect()}
    assert out[3].text is None and out[2].entities[0].surrogate in out[1].text and out[1].collisions == 0
    assert surrogates.collisions(surrogates.entity_pairs(df)).count() == 0
    assert surrogates.replace_entities(extra).count() == extra.count() and surrogates.surrogate_report(none).count() == 0
    untouched = surrogates.replace_entities(docs).alias("n").join(docs.alias("o"), "doc_id").filter("n.text <> o.text AND n.text IS NOT NULL")
    assert untouched.filter(F.col("doc_id") != 15).count() == 0


def test_surrogates_move_everything_apart(spark):
    keyed = surrogates.Keyed(b"k")
    for n in (2, 6, 7, 20, 1000):
        images = [keyed.number(i, n, b"t") for i in range(n)]
        assert sorted(images) == list(range(n)) and all(i != k for i, k in enumerate(images))
    s = surrogates.Surrogates(b"k")
    assert all(s.name(n, g) != n and s.name(n, g) in own for (g, _), own in surrogates.GIVEN.items() for n in own)
    shape = [a + b + c + d for a in "AEIOU" for b in surrogates.CONSONANTS for c in surrogates.CONSONANTS for d in "aeiou"]
    assert {"Anna", "Emma"} <= set(shape) and len({s.name(w, "f") for w in shape}) == len(shape)
    ips = [f"{a}.1.2.{b}" for a in (0, 7, 99, 230, 250) for b in range(200)]
    images = [s.ip(x) for x in ips]
    assert len(set(images)) == len(ips) and all((int(x.split(".")[0]) in (0, *range(224, 256))) == (int(y.split(".")[0]) in (0, *range(224, 256))) for x, y in zip(ips, images, strict=True))
    pairs = spark.createDataFrame([("name", "o1", "x"), ("name", "o2", "x"), ("name", "o2", "x"), ("ip", "o3", "x"), ("name", "o4", "y")], "kind string, original string, surrogate string")
    pairs = pairs.withColumn("image", F.col("surrogate"))
    assert [tuple(r) for r in surrogates.colliding(pairs).collect()] == [("name", "o2", True)]
    there = spark.createDataFrame([("ip", "p", "s1", "q"), ("ip", "q", "s2", "r"), ("name", "p", "s3", "q"), ("name", "q", "s4", "p")], pairs.schema)
    assert [tuple(r) for r in surrogates.colliding(there).collect()] == [("ip", "p", False)]
    s = surrogates.Surrogates(b"k")
    assert s.phone("+491701234567", None).startswith("+49") and s.phone("+15551234567", None).startswith("+1")
    assert [o for _, _, _, o, _ in s.apply("Mr 王伟 said Mr محمد علي came, Herr Łukasz Żółty")[1]] == ["王伟", "محمد علي", "Łukasz Żółty"]
    assert all(a != b for a, b in zip("ŁukaszŻółty", s.name("ŁukaszŻółty", "m"), strict=True))
    again = surrogates.Surrogates(b"k", {("name", s.digest("Smith")): 1})
    assert again.replace("name", "Smith", "m") != s.replace("name", "Smith", "m") and again.replace("name", "Jones", "m") == s.replace("name", "Jones", "m")


def test_later_mentions_of_a_name():
    s = surrogates.Surrogates(b"k")
    text = "Smith knew that Mrs Anna Smith came. Anna left, Smith stayed, Anna Smith slept; Smithson and Mr Young are young. Young!"
    new, found = s.apply(text)
    given, family = s.name("Anna Smith", "f").split(" ")
    assert [o for _, _, _, o, _ in found] == ["Anna Smith", "Anna", "Smith", "Anna Smith", "Young"]
    assert new.startswith(f"Smith knew that Mrs {given} {family} came. {given} left, {family} stayed, {given} {family} slept; Smithson") and new.endswith(" Young!")


# Pipeline -------------------------------------------------------------------------------------------------------------------


def test_pipeline_stages(spark, docs, none, tmp_path):
    import corpus_pipeline as p

    assert [n for n, _ in p.STAGES] == ["language_id", "line_dedup", "near_duplicates", "source_mix", "piece_encoding"]
    now, path = docs, str(tmp_path / "0")
    for k, (name, stage) in enumerate(p.STAGES):
        out = stage(spark, now, str(tmp_path))
        path = str(tmp_path / f"{k + 1}")
        out.write.parquet(path)
        nxt = spark.read.parquet(path)
        before, after = now.count(), nxt.count()
        if name == "language_id":
            assert {r.doc_id for r in nxt.collect()} == {r.doc_id for r in docs.collect()} - {1, 2, 3}
        if name == "line_dedup":
            kept = {r.doc_id: r.text for r in nxt.collect()}
            assert after == before and LINE not in kept[9].lower() and LINE not in kept[11].lower() and LINE in kept[12]
        if name == "near_duplicates":
            ids = {r.doc_id for r in nxt.collect() if r.doc_id is not None}
            assert ids == {c for _, _, c in class_brute([tuple(r) for r in now.collect()]) if c is not None} and after < before
        if name in ("source_mix", "piece_encoding"):
            assert after == before
        assert nxt.columns == docs.columns + (["ids"] if name == "piece_encoding" else [])
        assert stage(spark, none, str(tmp_path)).count() == 0
        now = nxt
    lib = library()
    assert all(r.ids == lib.encode(r.text or "") for r in now.collect())


def test_pipeline_keeps_the_mix_in_files(spark, tmp_path):
    """Written and read in any order, the rows of run() give the mix: each source within a block and the rounding of its target."""
    import corpus_pipeline as p

    data = [(i, f"the of and was that number {' '.join(f'{a}{i}' for a in 'pqrstuvw')}", "en", s, 60) for i, s in enumerate(["a"] * 400 + ["b"] * 100 + ["c"] * 25)]
    spark.createDataFrame(data, SCHEMA).write.parquet(str(tmp_path / "documents.parquet"))
    p.run(spark, str(tmp_path)).repartition(7).write.parquet(str(tmp_path / "out"))
    got = spark.read.parquet(str(tmp_path / "out")).orderBy("mix_order").collect()
    assert len(got) == len({r.mix_order for r in got}) and "ids" in got[0].asDict()
    n = {s: sum(r.source == s for r in got) for s in "abc"}
    total = sum(k**0.5 for k in n.values())
    for t in range(1, 1 + min(int(k**0.5 * total) for k in n.values())):  # until the first source ends
        for s in "abc":
            assert abs(sum(r.source == s for r in got[:t]) - t * n[s] ** 0.5 / total) < 2 * pfair_mix.BLOCK


def test_pipeline_against_brute_force(spark, tmp_path):
    """run() over whole files, against the stages' rules in plain Python; the model and the order of the mix are tested on their own."""
    import corpus_pipeline as p

    rng, i = random.Random(21), 0
    english = "the of and was that this with from have they which would there been their more about other".split()
    shared = [" ".join(rng.choices(english, k=9)) for _ in range(3)]
    data = [(1000, None), (1001, ""), (1002, "12345 67890"), (1003, "99 88 77")]
    for g in range(12):
        base = rng.choices(english, k=60)
        for _ in range(rng.choice((1, 1, 3))):
            w = list(base)
            for _ in range(rng.randint(0, 2)):
                w[rng.randrange(60)] = rng.choice(english)
            data.append((i := i + 1, " ".join(w[:30]) + "\n" + shared[g % 3] + "\n" + " ".join(w[30:])))
    rows_ = [(i, t, "en" if i < 1000 else None, "ab"[i % 2], len(t or "")) for i, t in data]
    spark.createDataFrame(rows_, SCHEMA).repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    got = {r.doc_id: r for r in p.run(spark, str(tmp_path)).collect()}
    left = [(i, t) for i, t in data if re.search("[a-z]", t or "")]
    holders = {x: [i for i, t in left if x in t.split("\n")] for _, t in left for x in t.split("\n") if len(x) >= 20}
    cut = [(i, "\n".join(x for x in t.split("\n") if len(holders.get(x, ())) < 3 or i == max(holders[x]))) for i, t in left]
    heads = {c for _, _, c in class_brute(cut)}
    lib, text = library(), dict(cut)
    assert set(got) == heads and all(r.text == text[i] and r.n_chars == len(text[i]) and r.ids == lib.encode(text[i]) for i, r in got.items())
    assert sorted(r.mix_order for r in got.values()) == sorted({r.mix_order for r in got.values()})


def test_sets_of_a_cut_block_are_sent_few_times(spark, monkeypatch):
    rng = np.random.default_rng(3)
    monkeypatch.setattr(prefix_join, "CHUNK", 64)
    base = [f"w{k}" for k in range(1500)]
    texts = []
    for k in range(400):  # one large group of near copies
        words = list(base)
        for at in rng.integers(0, 1500, 5):
            words[at] = f"x{k}-{at}"
        texts.append(" ".join(words))

    def written() -> int:
        time.sleep(1)  # the listener follows the tasks
        found = spark.sparkContext._jsc.sc().statusStore().executorList(True)
        return sum(found.apply(k).totalShuffleWrite() for k in range(found.size()))

    before = written()
    got = prefix_join.link_classes(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(8)).collect()
    assert {r.component_id for r in got} == {0}
    assert (written() - before) / sum(8 * r.n_shingles for r in got) < 1.6
