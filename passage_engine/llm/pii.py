"""Surrogates for personal data: keyed, of the same type, distinct and the same everywhere.

E-mail addresses, telephone, card and social-security numbers, IBANs, IP addresses and titled names
are found by pattern. What has a format (digits, letters and their cases, separators, script) gets a
surrogate by a keyed permutation of its own format, so different entities have different surrogates;
card numbers and IBANs keep valid checksums, IP addresses their ranges, telephone numbers their
country. Names are replaced word by word from lists by gender and script: a check over all given
and all family names of the corpus resolves collisions, so that each list is mapped one to one and
so are full names. As a family name has one surrogate, "Mr Keller" and "Mr Paul Keller" stay alike,
and so do spellings that differ in case.
"""

from __future__ import annotations

import hashlib
import hmac
import re
import unicodedata

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored, texts_of

KINDS = ("email", "iban", "card", "ssn", "ip", "phone", "name")
EMAIL = re.compile(r"(?<![\w.+-])([A-Za-z0-9][\w.+-]*)@((?:[A-Za-z0-9-]+\.)+[A-Za-z]{2,})", re.A)
IBAN = re.compile(r"\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b")
CARD = re.compile(r"(?<!\d)(?:\d{4}([ -]?)\d{4}\1\d{4}\1\d{1,7}|\d{4}([ -]?)\d{6}\2\d{5})(?!\d)")
SSN = re.compile(r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])")
IP = re.compile(r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\d.]*\d)")
PHONE = re.compile(r"(?<![\w.])(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?|\d{2,4}[ .-])\d{3}[ .-]?\d{3,4}(?!\w)|(?<![\w.])\+\d{7,15}(?!\w)")
COUNTRY = re.compile(r"\+(?:\d{1,3}(?=\D)|\d{2})")
NAME = re.compile(r"\b(Mr|Mrs|Ms|Miss|Sir|Lady|Madame|Monsieur|Herr|Frau|Señor|Señora|Г-н|Г-жа)(\.?\s)([^\W\d_]+(?:\s[A-ZÀ-ÞА-Я][^\W\d_]+)?)")
#: Fixed lists: titles of women; given names and family names by script, women's first.
WOMEN = frozenset(["Mrs", "Ms", "Miss", "Lady", "Madame", "Frau", "Señora", "Г-жа"])
GIVEN = {
    "LATIN": (["Anna", "Clara", "Elena", "Greta", "Helen", "Irene", "Julia", "Laura", "Maria", "Nora", "Paula", "Rosa", "Sara", "Vera"], ["Albert", "Bruno", "Carl", "David", "Erik", "Felix", "Georg", "Hugo", "Ivan", "Jonas", "Leon", "Martin", "Oscar", "Paul"]),
    "CYRILLIC": (["Анна", "Вера", "Дарья", "Елена", "Ирина", "Мария", "Нина", "Ольга"], ["Антон", "Борис", "Виктор", "Глеб", "Иван", "Олег", "Павел", "Юрий"]),
}
FAMILY = {
    "LATIN": (["Adler", "Bennet", "Castro", "Dumas", "Engel", "Ferrer", "Garner", "Holm", "Ibarra", "Jensen", "Keller", "Lambert", "Moreno", "Norton", "Olsen", "Porter", "Quint", "Romero", "Steiner", "Turner"],) * 2,
    "CYRILLIC": (["Волкова", "Зайцева", "Козлова", "Лебедева", "Орлова", "Соколова"], ["Волков", "Зайцев", "Козлов", "Лебедев", "Орлов", "Соколов"]),
}
CLASSES = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ")


def number(key: bytes, *parts: object) -> int:
    return int.from_bytes(hmac.new(key, "\x1f".join(map(str, parts)).encode("utf-8", "surrogatepass"), hashlib.sha256).digest()[:16], "big")


def permuted(text: str, key: bytes, tweak: str) -> str:
    """Keyed permutation of all strings of the same format: characters keep their class, others stay.

    A Feistel network over the two halves of the class characters, each with its own radix.
    """
    at = [(i, c, cls) for i, c in enumerate(text) for cls in CLASSES if c in cls]
    if not at:
        return text
    radix = [len(cls) for _, _, cls in at]
    digits = [cls.index(c) for _, c, cls in at]
    if len(at) == 1:
        digits = [(digits[0] + number(key, tweak, "one")) % radix[0]]
    half = len(at) // 2
    for r in range(8 if len(at) > 1 else 0):
        a, b = (range(half), range(half, len(at))) if r % 2 else (range(half, len(at)), range(half))
        n = number(key, tweak, r, len(at), *(digits[i] for i in b))
        for i in a:
            digits[i] = (digits[i] + n) % radix[i]
            n = n // radix[i] if n >> 32 else number(key, tweak, r, i, n)
    out = list(text)
    for (i, _, cls), d in zip(at, digits, strict=True):
        out[i] = cls[d]
    return "".join(out)


def iban_ok(text: str) -> bool:
    t = text.replace(" ", "")
    return 15 <= len(t) <= 34 and int("".join(str(int(c, 36)) for c in t[4:] + t[:4])) % 97 == 1


def surrogate(kind: str, text: str, key: bytes) -> str:
    """The surrogate of an entity that has a format of its own."""
    if kind == "email":
        local, _, domain = text.rpartition("@")
        host, _, top = domain.rpartition(".")
        return f"{permuted(local.lower(), key, 'local')}@{permuted(host.lower(), key, 'host')}.{top.lower()}"
    if kind == "card":
        digits = "".join(c for c in text if c.isdigit())
        body = permuted(digits[1:-1], key, "card" + digits[0])
        valid = int(digits[-1]) == _check_digit(digits[:-1])
        last = _check_digit(digits[0] + body)
        # an invalid number stays invalid, by as much
        shift = 0 if valid else (int(digits[-1]) - _check_digit(digits[:-1])) % 10
        new = iter(digits[0] + body + str((last + shift) % 10))
        return "".join(next(new) if c.isdigit() else c for c in text)
    if kind == "iban":
        body = permuted(text[4:], key, "iban" + text[:2])
        plain = (body + text[:2] + "00").replace(" ", "")
        return f"{text[:2]}{98 - int(''.join(str(int(c, 36)) for c in plain)) % 97:02d}{body}"
    if kind == "ip":
        a, rest = text.split(".", 1)
        v = 0
        for p in rest.split("."):
            v = v << 8 | int(p)
        left, right = v >> 12, v & 0xFFF
        for r in range(8):
            left, right = right, left ^ number(key, "ip", a, r, right) & 0xFFF
        v = left << 12 | right
        return f"{a}.{v >> 16}.{v >> 8 & 255}.{v & 255}"
    if kind == "phone" and (code := COUNTRY.match(text)):
        return code[0] + permuted(text[code.end() :], key, kind + code[0])
    return permuted(text, key, kind)


def _check_digit(body: str) -> int:
    return (10 - sum(int(d) if i % 2 else sum(divmod(2 * int(d), 10)) for i, d in enumerate(reversed(body)))) % 10


def script_of(text: str) -> str:
    for c in text:
        s = unicodedata.name(c, "").split(" ")[0]
        if c.isalpha() and s in GIVEN:
            return s
    return "LATIN"


Slot = tuple[str, str, str]


def slots_of(gender: str, name: str) -> list[tuple[Slot, str]]:
    """((list, gender, script), word without case) of each word; Latin family names know no gender."""
    words, out = name.split(), []
    for i, w in enumerate(words):
        script, family = script_of(w), i == len(words) - 1
        out.append((("family" if family else "given", "" if family and script == "LATIN" else gender, script), w.casefold()))
    return out


def word_surrogate(slot: Slot, word: str, attempt: int, key: bytes) -> str:
    """A word of the slot's list; beyond the lists' attempts letters of the same script are added."""
    kind, gender, script = slot
    pool = (FAMILY if kind == "family" else GIVEN)[script][0 if gender == "f" else 1]
    new = pool[number(key, "name", *slot, word, min(attempt, 8)) % len(pool)]
    vowels, others = ("aeiou", "nrstl") if script == "LATIN" else ("аеиоу", "нрстл")
    return new + "".join(vowels[int(d) % 5] + others[int(d) // 5] for d in (f"{attempt - 8:o}" if attempt >= 8 else ""))


def name_surrogate(gender: str, name: str, words: dict[tuple[Slot, str], str], key: bytes) -> str:
    """A name of the same gender, script, number of words and case of letters."""
    out = []
    for w, (slot, plain) in zip(name.split(), slots_of(gender, name), strict=True):
        new = words.get((slot, plain)) or word_surrogate(slot, plain, 0, key)
        out.append(new.upper() if w.isupper() and len(w) > 1 else new.lower() if w.islower() else new)
    return " ".join(out)


def entities(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) from left to right, not overlapping; earlier kinds win."""
    found: list[tuple[int, int, int]] = []
    if "@" in text:
        found += [(m.start(), 0, m.end()) for m in EMAIL.finditer(text)]
    found += [(m.start(), 1, m.end()) for m in IBAN.finditer(text) if iban_ok(m[0])]
    found += [(m.start(), 2, m.end()) for m in CARD.finditer(text)]
    found += [(m.start(), 3, m.end()) for m in SSN.finditer(text)]
    found += [(m.start(), 4, m.end()) for m in IP.finditer(text)]
    found += [(m.start(), 5, m.end()) for m in PHONE.finditer(text)]
    found += [(m.start(3), 6, m.end(3)) for m in NAME.finditer(text)]
    out: list[tuple[str, int, int]] = []
    for k in range(len(KINDS)):
        out += [(KINDS[k], s, e) for s, kk, e in found if kk == k and not any(a < e and s < b for _, a, b in out)]
    return sorted(out, key=lambda x: x[1])


def names_of(text: str) -> list[tuple[str, str]]:
    """(gender, name) of each titled name."""
    return [("f" if m[1] in WOMEN else "m", m[3]) for m in NAME.finditer(text)]


def resolve_words(docs: DataFrame, key: bytes, rounds: int = 4) -> DataFrame:
    """The distinct words of names of the corpus to surrogates, none of which two words of a slot share.

    In each round the smallest word of those with one surrogate keeps it and the others try the next;
    nothing is gathered but a count. Words that still share one after ``rounds`` take attempts of
    their own, by their rank among all such words and beyond all others, whose suffixes are distinct.
    Returns (kind, gender, script, word, attempt, surrogate); raises if two words share a surrogate.
    """
    slot = ["kind", "gender", "script"]

    def find(batches):
        for b in batches:
            got = sorted({x for t in texts_of(b) for n in names_of(t) for x in slots_of(*n)})
            cols = [*zip(*(s for s, _ in got), strict=True)] or [[], [], []]
            yield pa.record_batch([*(pa.array(c, pa.string()) for c in cols), pa.array([w for _, w in got], pa.string())], names=[*slot, "word"])

    def attempt(batches):
        for b in batches:
            rows = zip(*(b.column(c).to_pylist() for c in (*slot, "word", "attempt")), strict=True)
            yield b.append_column("surrogate", pa.array([word_surrogate(tuple(r[:3]), r[3], r[4], key) for r in rows], pa.string()))

    schema = "kind string, gender string, script string, word string, attempt int, surrogate string"
    words = docs.select("text").mapInArrow(find, "kind string, gender string, script string, word string").distinct().withColumn("attempt", F.lit(0))
    now = stored(words.mapInArrow(attempt, schema), "names")
    lost = F.col("kept").isNotNull() & ~((F.col("kept.word") == F.col("word")) & (F.col("kept.attempt") == F.col("attempt")))
    columns = [*slot, "word", "attempt"]

    def shared(now: DataFrame) -> DataFrame:
        return now.groupBy(*slot, "surrogate").agg(F.min(F.struct("attempt", "word")).alias("kept"), F.count("*").alias("n")).where("n > 1").drop("n")

    for _ in range(rounds):
        keep = shared(now)
        if keep.isEmpty():
            return now
        judged = now.join(keep, [*slot, "surrogate"], "left").withColumn("attempt", F.when(lost, F.col("attempt") + 1).otherwise(F.col("attempt")))
        now = stored(judged.select(*columns).mapInArrow(attempt, schema), "names")
    keep = shared(now)
    if keep.isEmpty():
        return now
    judged = stored(now.join(keep, [*slot, "surrogate"], "left").select(*columns, lost.alias("lost")), "judged")
    beyond = max(8, judged.agg(F.max("attempt")).first()[0] + 1)
    ranked = judged.where("lost").select(*slot, "word").orderBy(*slot, "word").rdd.zipWithIndex().map(lambda x: (*x[0], beyond + x[1]))
    own = docs.sparkSession.createDataFrame(ranked, "kind string, gender string, script string, word string, attempt int")
    now = stored(judged.where("not lost").select(*columns).union(own).mapInArrow(attempt, schema), "names")
    if not shared(now).isEmpty():
        raise ValueError("names share a surrogate")
    return now


def collected(words: DataFrame, most_names: int) -> dict[tuple[Slot, str], str]:
    """The table of words for a broadcast; raises beyond ``most_names`` rows."""
    n = words.count()
    if n > most_names:
        raise ValueError(f"{n} words of names are more than {most_names}")
    return {((r.kind, r.gender, r.script), r.word): r.surrogate for r in words.collect()}


def resolve_names(docs: DataFrame, key: bytes, rounds: int = 4, most_names: int = 1_000_000) -> DataFrame:
    """Distinct titled names of the corpus to (gender, name, surrogate)."""
    words = docs.sparkSession.sparkContext.broadcast(collected(resolve_words(docs, key, rounds), most_names))

    def run(batches):
        for b in batches:
            got = sorted({x for t in texts_of(b) for x in names_of(t)})
            yield pa.record_batch([pa.array([g for g, _ in got], pa.string()), pa.array([n for _, n in got], pa.string()), pa.array([name_surrogate(g, n, words.value, key) for g, n in got], pa.string())], names=["gender", "name", "surrogate"])

    return docs.select("text").mapInArrow(run, "gender string, name string, surrogate string").distinct()


def replace(text: str, key: bytes, words: dict[tuple[Slot, str], str]) -> tuple[str, list[tuple[str, int, int]]]:
    found = entities(text)
    titles = {m.start(3): "f" if m[1] in WOMEN else "m" for m in NAME.finditer(text)} if any(k == "name" for k, _, _ in found) else {}
    out, end = [], 0
    for kind, s, e in found:
        own = text[s:e]
        out += [text[end:s], name_surrogate(titles.get(s, "m"), own, words, key) if kind == "name" else surrogate(kind, own, key)]
        end = e
    return "".join([*out, text[end:]]), found


def pseudonymise(docs: DataFrame, key: bytes, most_names: int = 1_000_000) -> DataFrame:
    """Documents (doc_id, text) to (doc_id, text, n_entities, entities).

    entities lists kind:start:end in code points of the original. Null text stays null with no
    entities. The table of words of names is broadcast when it has at most ``most_names`` rows; beyond
    that this raises. Repeated rows stay; other columns are not read. The same key gives the same
    surrogates in every run.
    """
    names = docs.sparkSession.sparkContext.broadcast(collected(resolve_words(docs, key), most_names))

    def run(batches):
        for b in batches:
            got = [(None, []) if t is None else replace(t, key, names.value) for t in b.column("text").to_pylist()]
            yield pa.record_batch([b.column("doc_id"), pa.array([t for t, _ in got], pa.string()), pa.array([len(f) for _, f in got], pa.int64()), pa.array([",".join(f"{k}:{s}:{e}" for k, s, e in f) for _, f in got], pa.string())], names=["doc_id", "text", "n_entities", "entities"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, text string, n_entities long, entities string")
