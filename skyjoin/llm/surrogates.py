"""Replacement of personal data by keyed surrogates of the same type, gender, script and format.

Found entities: e-mail addresses, phone numbers, payment cards, IPv4 addresses, IBANs, national numbers (3-2-4 digits), secrets
after a name such as token or api_key, and person names after a title. A surrogate is the entity's image under a keyed
permutation, so equal entities have equal surrogates in every document (coreference) and different ones different surrogates
(distinctness) without a shared table:

* characters keep their class (lower, upper, digit, hexadecimal, script); the string as a number in mixed radix goes through
  a Feistel network over the next even number of bits, again until it is back in range;
* a card keeps its prefix-independent checksum distance (a valid number stays valid), an address its private or public range,
  a phone its country code with or without a gap behind it, an e-mail goes under the reserved name "example";
* a given name of the lists moves within the list of its gender and script; other names keep vowels, consonants and script
  and never become a listed one. A name is found after a title, in scripts without capitals too: a run of up to four ideographs, kana or
  syllables (three of a longer run), or two words. It is replaced wherever it stands later in the text, whole or by one of its
  words; a word that the text also has in small letters counts as no name.

The report first runs the collision check over all distinct entities; an original whose surrogate is another one's, or stands in the
corpus as an original of its kind itself (names apart, whose lists are small), gets that of the next tweak. collisions() checks a
table of entities: surrogates of more than one original, or originals with more than one surrogate.

The key is an argument; DEMO_KEY only makes results repeatable. Edge cases: null texts stay null, empty ones empty; overlapping finds go
to the earlier, then longer one; nothing outside the finds changes; the permutations have no fixed points, so no image equals its
original unless its format has one string alone; equal texts have equal results, rows are replaced one by one; extra columns stay, one
called as an output is replaced; an empty table gives an empty one.
"""

from __future__ import annotations

import hashlib
import re
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import checkpointed, chunks, returning, with_fields

DEMO_KEY = b"replace this key"
ROUNDS = 8

# Given names by gender and script; titles by gender; names of secrets; alphabets of character classes.
GIVEN = {
    ("f", "latin"): "Alice Anna Carmen Claire Clara Emma Hannah Ines Julia Laura Lena Lucia Maria Marie Nora Paula Rosa Sara Sofia Sophie".split(),
    ("m", "latin"): "Adam Alexander Andre Carlos Daniel David Diego Felix Hans Hugo Jean John Jonas Karl Louis Lucas Paul Pedro Peter Thomas".split(),
    ("f", "cyrillic"): "Анна Вера Дарья Елена Ирина Мария Наталья Ольга Софья Татьяна".split(),
    ("m", "cyrillic"): "Алексей Андрей Борис Виктор Дмитрий Иван Михаил Николай Павел Сергей".split(),
    ("f", "greek"): "Άννα Ελένη Ειρήνη Κατερίνα Μαρία Σοφία".split(),
    ("m", "greek"): "Αλέξανδρος Γιώργος Δημήτρης Κώστας Νίκος Πέτρος".split(),
}
TITLES = {"f": "Mrs Ms Miss Madam Frau Señora Señorita Sra Srta Madame Mademoiselle Mme Mlle г-жа госпожа κυρία".split(), "m": "Mr Mister Sir Herr Señor Sr Monsieur г-н господин κύριος".split(), "": "Dr Prof".split()}
LISTED = frozenset(n for own in GIVEN.values() for n in own)
SECRET = "token|secret|password|passwd|api[_-]?key|access[_-]?key"
VOWELS = "aeiou"
CONSONANTS = "bcdfghjklmnpqrstvwxyz"
LATIN_LOWER = "".join(chr(c) for c in range(0xDF, 0x100) if c != 0xF7)
LATIN_UPPER = "".join(chr(c) for c in range(0xC0, 0xDF) if c != 0xD7)
CYRILLIC = "".join(chr(c) for c in range(0x430, 0x450))
GREEK = "".join(chr(c) for c in range(0x3B1, 0x3CA) if c != 0x3C2)
#: Further blocks of letters, each in small letters, capitals and letters without case: Latin, accented Greek, more Cyrillic, Armenian,
#: Hebrew, Arabic, Devanagari, Thai, Georgian, kana, ideographs, Hangul syllables.
BLOCKS = [(0x100, 0x250), (0x386, 0x390), (0x3AA, 0x3D0), (0x400, 0x410), (0x450, 0x530), (0x531, 0x588), (0x5D0, 0x5EB), (0x620, 0x64B), (0x904, 0x93A), (0xE01, 0xE2F), (0x10D0, 0x10FB), (0x1E00, 0x1F00), (0x3041, 0x3097), (0x30A1, 0x30FB), (0x4E00, 0xA000), (0xAC00, 0xD7A4)]
CLASSES = ["0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", LATIN_LOWER, LATIN_UPPER, CYRILLIC, CYRILLIC.upper(), GREEK, GREEK.upper()]
_HELD = frozenset("".join(CLASSES))
for _a, _b in BLOCKS:
    _letters = [c for c in map(chr, range(_a, _b)) if c.isalpha() and c not in _HELD]
    _cases = ([c for c in _letters if c.islower()], [c for c in _letters if c.isupper()], [c for c in _letters if not c.islower() and not c.isupper()])
    CLASSES += ["".join(k) for k in _cases if len(k) > 1]
SOUNDS = [VOWELS, CONSONANTS, VOWELS.upper(), CONSONANTS.upper(), *CLASSES[3:]]
HEX = ["0123456789abcdef", "0123456789ABCDEF"]
#: The classes by what is replaced.
ALPHABETS = {"any": CLASSES, "sounds": SOUNDS, "hex": HEX[:1], "HEX": HEX[1:]}
# Country codes of one and of two digits; all others have three.
COUNTRY_ONE = frozenset("17")
COUNTRY_TWO = frozenset("20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split())
#: Tweaks that the collision check tries; originals that it settles at most (no name or number is left out of the replacement).
TRIES, MOST_AGAIN = 8, 100_000

_TITLE = "|".join(sorted((t for own in TITLES.values() for t in own), key=len, reverse=True))
_NAME = r"[^\W\d_][^\W\d_'’-]*"
PATTERNS = {
    "email": re.compile(r"(?<![\w.+%-])[\w+%-]+(?:\.[\w+%-]+)*@[^\W_](?:[\w-]*[^\W_])?(?:\.[^\W_](?:[\w-]*[^\W_])?)+"),
    "iban": re.compile(r"(?<![\w])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![\w])"),
    "secret": re.compile(rf"(?i:\b(?:{SECRET}))\s*[=:]\s*[\"']?([A-Za-z0-9+/_.-]{{8,}})"),
    "card": re.compile(r"(?<![\w.-])\d(?:[ -]?\d){12,18}(?![\w-])"),
    "ip": re.compile(r"(?<![\w.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\w]|\.\d)"),
    "national": re.compile(r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])"),
    "phone": re.compile(r"(?<![\w.])(?:\+(?P<country>\d{1,3})[ .-]?)?\(?\d{2,4}\)?[ .-]\d{3,4}[ .-]?\d{3,4}(?![\w])|(?<![\w.])\+\d{8,15}(?![\w])"),
    "name": re.compile(rf"(?<!\w)(?P<title>{_TITLE})\.?\s+(?=(?P<names>{_NAME}(?:[ ]{_NAME}){{0,2}}))"),
}
_TITLES = frozenset(t for own in TITLES.values() for t in own)
_WORD = re.compile(r"\w+")
_MARKS = re.compile(r"[@0-9]")
_SECRET = re.compile(rf"(?i){SECRET}")


@lru_cache(maxsize=100_000)
def class_of(c: str, alphabet: str) -> str | None:
    """The class of a character among those of an alphabet."""
    return next((k for k in ALPHABETS[alphabet] if c in k), None)


def country_length(digits: str) -> int:
    """Digits of the country code that a number without its plus sign begins with."""
    return 1 if digits[:1] in COUNTRY_ONE else 2 if digits[:2] in COUNTRY_TWO else 3


def named(words: list[str]) -> str:
    """The words behind a title that are the name; none if the first one is in small letters."""
    out: list[str] = []
    for w in words:
        if w[0].isupper():
            out.append(w)
            continue
        if w[0].islower() or not w[0].isalpha():
            break
        if ord(w[0]) >= 0x3041:  # written without gaps
            run = re.match(r"[\u3041-\ud7a3]+", w)[0]
            return " ".join([*out, run if len(run) <= 4 else run[:3]])
        if len(out) == 2:
            break
        out.append(w)
    return " ".join(out)


class Keyed:
    """Permutations of strings that keep each character's class, under one key."""

    def __init__(self, key: bytes):
        self.key = hashlib.blake2b(key, digest_size=32).digest()

    def number(self, value: int, size: int, tweak: bytes) -> int:
        """The image of value under a permutation of 0 .. size - 1 that leaves nothing in its place.

        The value's place in a keyed order is shifted by a keyed number and read back: still a permutation, without fixed points.
        """
        if size < 2:
            return value
        half = max(1, -(-(size - 1).bit_length() // 2))
        low, mask = (half + 7) // 8, (1 << half) - 1

        def mixed(b: int, r: int) -> int:
            h = hashlib.blake2b(b.to_bytes(low, "big") + bytes([r]) + tweak, key=self.key, digest_size=min(64, low + 8)).digest()
            return int.from_bytes(h, "big") & mask

        def ordered(value: int, back: bool) -> int:
            while True:
                a, b = value >> half, value & mask
                for r in reversed(range(ROUNDS)) if back else range(ROUNDS):
                    a, b = (b ^ mixed(a, r), a) if back else (b, a ^ mixed(b, r))
                value = a << half | b
                if value < size:
                    return value

        shift = 1 + int.from_bytes(hashlib.blake2b(b"shift" + tweak, key=self.key, digest_size=min(64, low * 2 + 8)).digest(), "big") % (size - 1)
        return ordered((ordered(value, False) + shift) % size, True)

    def text(self, text: str, kind: str, alphabet: str = "any") -> str:
        """The image of a string; characters of no class stay."""
        out = list(text)
        todo = [(i, own) for i, c in enumerate(text) if (own := class_of(c, alphabet))]
        # Long strings go in parts, each under what stands before it in the original.
        for at in range(0, len(todo), 64):
            part = todo[at : at + 64]
            value, size = 0, 1
            for i, own in part:
                value, size = value * len(own) + own.index(text[i]), size * len(own)
            shape = "".join(own[0] for _, own in part)
            tweak = hashlib.blake2b(f"{kind}\0{shape}\0{text[: part[0][0]] if at else ''}".encode(), digest_size=16).digest()
            image = self.number(value, size, tweak)
            for i, own in reversed(part):
                image, k = divmod(image, len(own))
                out[i] = own[k]
        return "".join(out)


def walked(image, value, inside):
    """image(value), image(image(value)), ...: the first inside a part of the space. On that part it is a permutation again."""
    value = image(value)
    while not inside(value):
        value = image(value)
    return value


def check_digit(digits: str) -> int:
    """The digit that makes digits plus it a valid card number."""
    total = sum(int(c) if i % 2 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(digits)))
    return -total % 10


def _digits_in(text: str, digits: str) -> str:
    new = iter(digits)
    return re.sub(r"\d", lambda _: next(new), text)


class Surrogates:
    """Finds and replaces the entities of texts."""

    def __init__(self, key: bytes = DEMO_KEY, again: dict[tuple[str, str], int] | None = None):
        """again: (kind, digest of an original) to the number of the tweak that it takes, where the first one collides."""
        self.key, self.again = key, again or {}
        self.keyed = Keyed(key)
        self.replace = lru_cache(maxsize=200_000)(self._replace)

    def email(self, text: str) -> str:
        local, _, domain = text.rpartition("@")
        # The whole address is one string, so that addresses differ if any part does.
        image = self.keyed.text(f"{local}@{domain}", "email")
        return image + ".example"

    def card(self, text: str) -> str:
        digits = re.sub(r"\D", "", text)
        gap = (int(digits[-1]) - check_digit(digits[:-1])) % 10
        body = self.keyed.text(digits[:-1], f"card{gap}")
        return _digits_in(text, body + str((check_digit(body) + gap) % 10))

    @staticmethod
    def range(v: int) -> str:
        if v >> 24 == 0 or v >> 28 >= 14:
            return "reserved"
        return "private" if v >> 24 in (10, 127) or v >> 20 == 172 << 4 | 1 or v >> 16 == 192 << 8 | 168 else "public"

    def ip(self, text: str) -> str:
        a, b, c, d = map(int, text.split("."))
        value = a << 24 | b << 16 | c << 8 | d
        for top, bits in ((10, 24), (172 << 4 | 1, 20), (192 << 8 | 168, 16), (127, 24)):
            if value >> bits == top:
                value = top << bits | self.keyed.number(value & ((1 << bits) - 1), 1 << bits, b"ip")
                break
        else:  # public addresses stay public, reserved ones reserved
            kind = self.range(value)
            value = walked(lambda v: self.keyed.number(v, 1 << 32, b"ip"), value, lambda v: self.range(v) == kind)
        return ".".join(str(value >> k & 255) for k in (24, 16, 8, 0))

    def phone(self, text: str, country: str | None) -> str:
        if not country and text.startswith("+"):
            country = text[1 : 1 + country_length(text[1:])]
        head = text.index(country) + len(country) if country else 0
        return text[:head] + self.keyed.text(text[head:], f"phone{country or ''}")

    def iban(self, text: str) -> str:
        return text[:2] + self.keyed.text(text[2:], f"iban{text[:2]}")

    def secret(self, text: str) -> str:
        # Lower hexadecimal, upper, other: each part of the strings of a format is mapped onto itself.
        kind = lambda t: next((i for i, k in enumerate(HEX) if all(c in k for c in t)), len(HEX))
        own = kind(text)
        return walked(lambda t: self.keyed.text(t, "secret", ("hex", "HEX", "any")[own]), text, lambda t: kind(t) == own)

    def word(self, word: str, gender: str) -> str:
        """The image of a word of a name, wherever in the name it stands. Listed names and others don't meet."""
        listed = [(g, s) for (g, s), names in GIVEN.items() if word in names]
        if not listed:
            return walked(lambda t: self.keyed.text(t, "family", "sounds"), word, lambda t: t not in LISTED)
        # A given name of the other gender's list only, as after a neutral title, keeps its own gender.
        group = next((x for x in listed if x[0] == gender), listed[0])
        names = GIVEN[group]
        return names[self.keyed.number(names.index(word), len(names), f"given{group}".encode())]

    def name(self, text: str, gender: str) -> str:
        return " ".join(self.word(w, gender) for w in text.split(" "))

    def digest(self, text: str) -> str:
        return hashlib.blake2b(text.encode(), key=self.keyed.key, digest_size=16).hexdigest()

    def _replace(self, kind: str, text: str, extra: str | None) -> str:
        if self.again and (n := self.again.get((kind, self.digest(text)))):
            return Surrogates(self.key + b"\0again%d" % n).replace(kind, text, extra)
        if kind == "phone":
            return self.phone(text, extra)
        if kind == "name":
            return self.name(text, extra or "")
        return {"email": self.email, "card": self.card, "ip": self.ip, "iban": self.iban, "secret": self.secret, "national": lambda t: self.keyed.text(t, "national")}[kind](text)

    def find(self, text: str) -> list[tuple[int, int, str, str | None]]:
        """(start, end, kind, extra) of each entity, without overlaps, in order."""
        found: list[tuple[int, int, str, str | None]] = []
        if _MARKS.search(text):
            if "@" in text:
                found += [(*m.span(), "email", None) for m in PATTERNS["email"].finditer(text)]
            for kind in ("iban", "card", "ip", "national", "phone"):
                found += [(*m.span(), kind, m.groupdict().get("country")) for m in PATTERNS[kind].finditer(text)]
        if _SECRET.search(text):
            found += [(*m.span(1), "secret", None) for m in PATTERNS["secret"].finditer(text)]
        known: dict[str, tuple[int, str]] = {}  # names and their words, to the end of the first find
        for m in PATTERNS["name"].finditer(text):
            if name := named(m["names"].split(" ")):
                gender = next(g for g, own in TITLES.items() if m["title"] in own)
                end = m.start("names") + len(name)
                found.append((m.start("names"), end, "name", gender))
                for w in {name, *(w for w in name.split(" ") if len(w) > 2 and w not in _TITLES)}:
                    known.setdefault(w, (end, gender))
        if known:
            found += self.mentions(text, known)
        out, end = [], 0
        order = {k: i for i, k in enumerate(("secret", *PATTERNS))}
        for x in sorted(found, key=lambda x: (x[0], -x[1], order[x[2]])):
            if x[0] >= end:
                out.append(x)
                end = x[1]
        return out

    @staticmethod
    def mentions(text: str, known: dict[str, tuple[int, str]]) -> list[tuple[int, int, str, str | None]]:
        """Places behind its first find where a name, or a word of it that the text has in capitals only, stands without a title."""
        small = {w for w in _WORD.findall(text) if w[0].islower()}
        wanted = sorted((w for w in known if " " in w or w.lower() not in small), key=len, reverse=True)
        if not wanted:
            return []
        pattern = re.compile(rf"(?<!\w)(?:{'|'.join(map(re.escape, wanted))})(?!\w)")
        return [(*m.span(), "name", known[m[0]][1]) for m in pattern.finditer(text, min(known[w][0] for w in wanted)) if m.start() >= known[m[0]][0]]

    def apply(self, text: str) -> tuple[str, list[tuple[int, int, str, str, str]]]:
        """The new text, and (start, end, kind, original, surrogate) of each entity by its place in the old one."""
        found = self.find(text)
        if not found:
            return text, []
        parts, at, entities = [], 0, []
        for start, end, kind, extra in found:
            original = text[start:end]
            new = self.replace(kind, original, extra)
            parts += [text[at:start], new]
            entities.append((start, end, kind, original, new))
            at = end
        return "".join([*parts, text[at:]]), entities


_ENTITY = pa.list_(pa.struct([("start", pa.int32()), ("length", pa.int32()), ("kind", pa.string()), ("surrogate", pa.string())]))
_ENTITY_TYPE = T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("length", T.IntegerType()), T.StructField("kind", T.StringType()), T.StructField("surrogate", T.StringType())]))


def replace_entities(docs: DataFrame, key: bytes = DEMO_KEY, again: dict | None = None) -> DataFrame:
    """docs with the entities of text replaced, and entities (place, kind, surrogate; never the original) beside it."""
    schema = with_fields(docs.schema, [T.StructField("entities", _ENTITY_TYPE)])
    names = schema.names[:-1]

    def run(batches):
        s = Surrogates(key, again)
        for whole in batches:
            place = whole.schema.get_field_index("text")
            for batch in chunks(whole, place):
                done = [(None, []) if t is None else s.apply(t) for t in batch.column(place).to_pylist()]
                entities = pa.array([[{"start": a, "length": b - a, "kind": k, "surrogate": new} for a, b, k, _, new in e] for _, e in done], _ENTITY)
                columns = [pa.array([t for t, _ in done], pa.string()) if n == "text" else batch.column(batch.schema.get_field_index(n)) for n in names]
                yield pa.RecordBatch.from_arrays([*columns, entities], [*names, "entities"])

    return docs.mapInArrow(returning(run), schema)


def entity_pairs(docs: DataFrame, key: bytes = DEMO_KEY, again: dict | None = None) -> DataFrame:
    """(kind, original, surrogate, image) of each find, for checks: keyed digests, but for the surrogate itself."""

    def run(batches):
        s = Surrogates(key, again)
        for whole in batches:
            for batch in chunks(whole, 0):
                rows = [(k, s.digest(o), new, s.digest(new)) for t in batch.column(0).to_pylist() if t for _, _, k, o, new in s.apply(t)[1]]
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.string()) for i in range(4)], ["kind", "original", "surrogate", "image"])

    return docs.select("text").mapInArrow(returning(run), "kind string, original string, surrogate string, image string")


def collisions(pairs: DataFrame) -> DataFrame:
    """Surrogates of several originals and originals of several surrogates within a kind: empty if all is well."""
    distinct = pairs.select("kind", "original", "surrogate").distinct()
    shared = distinct.groupBy("kind", F.col("surrogate").alias("value")).agg(F.count("*").alias("n")).filter("n > 1").withColumn("what", F.lit("surrogate"))
    split = distinct.groupBy("kind", F.col("original").alias("value")).agg(F.count("*").alias("n")).filter("n > 1").withColumn("what", F.lit("original"))
    return shared.unionByName(split)


def colliding(pairs: DataFrame) -> DataFrame:
    """(kind, original, taken) that need another tweak: all originals but the first of a surrogate (taken), and, names apart, those whose
    surrogate is an original too."""
    distinct = pairs.distinct()
    shared = distinct.groupBy("kind", "surrogate").agg(F.count("*").alias("n"), F.min("original").alias("first")).filter("n > 1").drop("n")
    taken = distinct.join(shared, ["kind", "surrogate"]).filter(F.col("original") != F.col("first")).select("kind", "original", F.lit(True).alias("taken"))
    there = distinct.filter("kind <> 'name'").select("kind", F.col("original").alias("image")).distinct()
    reused = distinct.join(there, ["kind", "image"], "left_semi").select("kind", "original", F.lit(False).alias("taken"))
    return taken.unionByName(reused).groupBy("kind", "original").agg(F.max("taken").alias("taken"))


def settled(docs: DataFrame, key: bytes = DEMO_KEY) -> tuple[dict[tuple[str, str], int], int]:
    """Tweak numbers of the originals that collided, by the check over all distinct entities until nothing collides; and the surrogates left
    that stand in the corpus as originals. Permutations don't meet, so few originals ever do; more than MOST_AGAIN is an error."""
    again: dict[tuple[str, str], int] = {}
    for turn in range(TRIES + 1):
        found = colliding(checkpointed(entity_pairs(docs, key, again).distinct()))
        rows = found.orderBy(F.desc("taken"), "kind", "original").limit(MOST_AGAIN + 1).collect()
        if not rows or turn == TRIES and not rows[0].taken:
            return again, len(rows)
        if len(rows) > MOST_AGAIN or turn == TRIES:
            raise RuntimeError(f"{len(rows)} or more originals collide after {turn} tweaks")
        for r in rows:
            again[r.kind, r.original] = again.get((r.kind, r.original), 0) + 1
    raise AssertionError


def surrogate_report(docs: DataFrame, key: bytes = DEMO_KEY) -> DataFrame:
    """What op7 returns: doc_id, the new text, n_entities, the entities, and the collisions that the check over the whole table left."""
    again, left = settled(docs, key)
    out = replace_entities(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), key, again)
    return out.select("doc_id", "text", F.size("entities").alias("n_entities"), "entities", F.lit(left).cast("long").alias("collisions"))
