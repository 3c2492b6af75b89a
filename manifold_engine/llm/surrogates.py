"""PII surrogates: keyed, type-consistent replacements that keep format, script and gender.

Every replacement is a keyed permutation of the entity's own space, so two
distinct entities of a type never meet in one surrogate and equal ones always
do, in any document and on any executor, with nothing shared but the key:

* mail addresses, secrets, phone numbers, addresses of hosts: a Feistel network
  over the digits and letters, each in its own alphabet, punctuation kept;
* card numbers with a valid check digit stay valid, others stay invalid; account
  numbers keep their country and get the check digits of what they became;
* first names of the lexicon are permuted among the names of their gender and
  script; other name parts have their vowels and consonants permuted among the
  vowels and consonants of their script, so the length and case stay and the
  same family name maps alike with or without a first name.

A person found once is known in the rest of the text: a later mention by family
or first name alone is replaced too, part by part, so it still reads as the same
person.

``collisions`` states the check over a whole table of entities: it returns the
surrogates that two distinct entities share (none by construction).  ``checked``
runs it over what is about to be handed on and refuses a table that fails.
"""

from __future__ import annotations

import hashlib
import ipaddress
import re
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..spool import spool
from . import grams
from .arrowmap import append_columns

# First names by script and gender.
FIRST_NAMES = {
    ("latin", "f"): "Anna Maria Emma Julia Laura Sophie Clara Marie Elena Lucia Alice Helen Sarah Karin Petra Isabel María Lucía Carmen Giulia Chiara Chloé Ingrid Astrid Olga Svetlana Yuki Keiko Priya Fatima Aisha Leila".split(),
    ("latin", "m"): "John Peter Paul Thomas Martin Carlos Pierre Hans Luis Jack David Simon Robert Michael Andrew Stefan José Diego Marco Giovanni Lars Björn Ivan Sergei Dmitri Akira Hiroshi Kenji Rajesh Ahmed Omar Yusuf".split(),
    ("cyrillic", "f"): "Анна Мария Елена Ольга Ирина Наталья Татьяна Светлана".split(),
    ("cyrillic", "m"): "Иван Пётр Сергей Алексей Дмитрий Николай Андрей Михаил".split(),
    ("greek", "f"): "Μαρία Ελένη Άννα Σοφία".split(),
    ("greek", "m"): "Γιώργος Νίκος Κώστας Πέτρος".split(),
}
# Forms of address by gender (None: either).
TITLES = {"Mr": "m", "Mrs": "f", "Ms": "f", "Miss": "f", "Dr": None, "Prof": None, "Herr": "m", "Frau": "f", "Monsieur": "m", "Madame": "f", "Señor": "m", "Señora": "f", "Sr": "m", "Sra": "f", "Г-н": "m", "Г-жа": "f", "Κύριος": "m", "Κυρία": "f"}
# Vowels and consonants by script.
LETTERS = {
    "latin": ("aeiou", "bcdfghjklmnpqrstvwxyz"),
    "latin marks": ("áàâäéèêëíìîïóòôöúùûü", "çñ"),
    "cyrillic": ("аеёиоуыэюя", "бвгджзйклмнпрстфхцчшщ"),
    "greek": ("αεηιουω", "βγδζθκλμνξπρστφχψ"),
    "greek marks": ("άέήίόύώ", ""),
}
DIGITS, HEX, UPPER36, LOWER36 = "0123456789", "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", "abcdefghijklmnopqrstuvwxyz0123456789"

_NAME = r"[^\W\d_][^\W\d_]+(?:[-'’][^\W\d_]+)*"
_PATTERNS = [
    ("email", r"[A-Za-z0-9][A-Za-z0-9._%+\-]{0,63}@(?:[A-Za-z0-9\-]{1,63}\.)+[A-Za-z]{2,24}"),
    ("aws_key", r"(?<![A-Za-z0-9])A[KS]IA[A-Z0-9]{16}(?![A-Za-z0-9])"),
    ("secret", r"(?<=[\"'])(?:[0-9a-f]{32,64}|[0-9A-F]{32,64})(?=[\"'])"),
    ("ipv4", r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)\.){3}(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)(?![\d]|\.\d)"),
    ("iban", r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])"),
    ("ipv6", r"(?<![\w:.])[0-9A-Fa-f]{0,4}(?::[0-9A-Fa-f]{0,4}){2,7}(?![\w:.])"),
    ("phone", r"\+\d{1,3}[ \-]?(?:\(\d{2,4}\)[ \-]?)?\d{2,4}(?:[ \-]?\d{2,4}){1,3}(?!\d)|(?<![\w\-+.])(?:\(\d{3}\) ?|\d{3}[\-.])\d{3}[\-.]\d{4}(?![\w\-])"),
    ("card", r"(?<!\d)\d{4}(?:[ \-]?\d{4}){3}(?!\d)"),
    ("national_id", r"(?<![\d\-])\d{3}-\d{2}-\d{4}(?![\d\-])"),
]
_RULES = re.compile("|".join(f"(?P<{n}>{p})" for n, p in _PATTERNS))
_FIRST = "|".join(sorted({n for own in FIRST_NAMES.values() for n in own}, key=len, reverse=True))
_PEOPLE = re.compile(rf"\b(?P<title>{'|'.join(sorted(map(re.escape, TITLES), key=len, reverse=True))})\.? (?P<titled>{_NAME}(?: {_NAME})?)|\b(?P<named>(?:{_FIRST}) {_NAME})\b")


class Keyed:
    """Permutations under one key."""

    def __init__(self, key: bytes):
        self.key = key

    def _number(self, tag: str, *parts) -> int:
        h = hashlib.blake2b("\x1f".join([tag, *map(str, parts)]).encode(), key=self.key[:64], digest_size=16)
        return int.from_bytes(h.digest(), "big")

    @lru_cache(maxsize=512)
    def order(self, tag: str, items: str | tuple) -> dict:
        """A permutation of a small alphabet."""
        return dict(zip(items, sorted(items, key=lambda x: self._number(tag, x))))

    def digits(self, tag: str, values: list[int], sizes: list[int]) -> list[int]:
        """A permutation of mixed-radix numbers: alternating halves, each shifted by a keyed hash of the other."""
        n = len(values)
        if n == 1:
            return [self.order(tag, tuple(range(sizes[0])))[values[0]]]
        cut = n // 2
        halves = [list(values[:cut]), list(values[cut:])]
        dims = [sizes[:cut], sizes[cut:]]
        for r in range(10):
            side = r % 2
            shift = self._number(tag, r, tuple(sizes), tuple(halves[1 - side]))
            out = []
            for v, m in zip(halves[side], dims[side]):
                shift, s = divmod(shift, m)
                shift = shift or self._number(tag, r, len(out), tuple(halves[1 - side]))
                out.append((v + s) % m)
            halves[side] = out
        return halves[0] + halves[1]

    def letters(self, tag: str, text: str, alphabets: list[str]) -> str:
        """Each character moves within its own alphabet; others stay."""
        at, vals, sizes, own = [], [], [], []
        for i, c in enumerate(text):
            for a in alphabets:
                if c in a:
                    at.append(i)
                    vals.append(a.index(c))
                    sizes.append(len(a))
                    own.append(a)
                    break
        if not at:
            return text
        out = list(text)
        for i, a, v in zip(at, own, self.digits(tag, vals, sizes)):
            out[i] = a[v]
        return "".join(out)

    # entity types

    def email(self, text: str) -> str:
        local, _, host = text.rpartition("@")
        stem, dot, top = host.rpartition(".")
        both = self.letters("email", f"{local}@{stem}", [DIGITS, LOWER36[:26], UPPER36[:26]])
        return both + dot + top

    def ipv4(self, text: str) -> str:
        n = [int(x) for x in text.split(".")]

        def kind(p):
            return p[0] in (0, 10, 127) and p[0] or (p[0] == 192 and p[1] == 168) and -1 or (p[0] == 172 and 16 <= p[1] < 32) and -2 or p[0] >= 224 and -3 or -4

        out = self.digits("ipv4", n, [256] * 4)
        while kind(out) != kind(n):  # walks its cycle back into the same class
            out = self.digits("ipv4", out, [256] * 4)
        return ".".join(map(str, out))

    def phone(self, text: str) -> str:
        """A country code stays; a number without one has digits alone to move."""
        m = re.match(r"\+\d{1,3}(?=[ \-(])|\+\d|", text)
        return m[0] + self.letters("phone", text[m.end() :], [DIGITS])

    def ipv6(self, text: str) -> str:
        """Digits and letters of every group move among their like, so its form and the place of ``::`` stay."""
        return self.letters("ipv6", text, [DIGITS, HEX[10:], HEX[10:].upper()])

    def iban(self, text: str) -> str:
        """Country kept, account moved, check digits set anew."""
        raw = text.replace(" ", "")
        body = self.letters(f"iban {raw[:2]}", raw[4:], [DIGITS, UPPER36[:26]])
        new = iter(f"{raw[:2]}{98 - _mod97(raw[:2] + '00' + body):02d}{body}")
        return re.sub(r"[^ ]", lambda m: next(new), text)

    def card(self, text: str) -> str:
        raw = re.sub(r"\D", "", text)
        fine = _luhn(raw)
        out = [int(c) for c in raw]
        if fine:
            body = self.digits("card", out[:-1], [10] * (len(out) - 1))
            out = body + [next(c for c in range(10) if _luhn("".join(map(str, body)) + str(c)))]
        else:
            out = self.digits("card x", out, [10] * len(out))
            while _luhn("".join(map(str, out))):
                out = self.digits("card x", out, [10] * len(out))
        it = iter(out)
        return re.sub(r"\d", lambda m: str(next(it)), text)

    def aws_key(self, text: str) -> str:
        return text[:4] + self.letters("aws", text[4:], [UPPER36])

    def secret(self, text: str) -> str:
        """Digits alone, with small and with capital letters are three classes, each mapped onto itself."""
        if text.isdigit():
            return self.letters("secret digits", text, [DIGITS])
        alphabet = HEX if text == text.lower() else HEX.upper()
        out = self.letters("secret", text, [alphabet])
        while out.isdigit():
            out = self.letters("secret", out, [alphabet])
        return out

    def national_id(self, text: str) -> str:
        return self.letters("id", text, [DIGITS])

    def word(self, text: str) -> str:
        """A name part: a lexicon name within its gender and script, else letters within vowels and consonants."""
        for (script, gender), names in FIRST_NAMES.items():
            if text in names:
                return self.order(f"first {script} {gender}", tuple(names))[text]
        known = [a for pair in LETTERS.values() for a in pair if a]
        out = self.letters("name", text, known + [a.upper() for a in known])
        while any(out in names for names in FIRST_NAMES.values()):  # stay out of the lexicon, which has its own permutation
            out = self.letters("name", out, known + [a.upper() for a in known])
        return out

    def person(self, text: str) -> str:
        return " ".join(map(self.word, text.split(" ")))


def _luhn(number: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(number)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def _mod97(number: str) -> int:
    """Remainder of an account number, country and check digits moved behind, letters as two digits."""
    return int("".join(str(int(c, 36)) for c in number[4:] + number[:4])) % 97


def _real(kind: str, value: str) -> bool:
    """Whether a candidate is what it looks like."""
    if kind == "iban":
        return _mod97(value.replace(" ", "")) == 1
    if kind == "ipv6":
        try:
            return len(ipaddress.IPv6Address(value).exploded) > 0 and sum(c != ":" for c in value) > 2
        except ValueError:
            return False
    return True


_HINT = re.compile(r"[@+]|AKIA|ASIA|\d{3}|\d\.\d|[\"'][0-9A-Fa-f]{8}|[0-9A-Fa-f]:[0-9A-Fa-f:]|[A-Z]{2}\d{2}")
_NAME_HINT = re.compile(rf"\b(?:{'|'.join(sorted(map(re.escape, TITLES), key=len, reverse=True))})\b|\b(?:{_FIRST}) ")


_WORD = re.compile(_NAME)


def _mentions(text: str, people: list[tuple[int, int]]) -> list[tuple[int, int, str]]:
    """Later and earlier mentions of found persons by one of their names."""
    parts = {w for s, e in people for w in text[s:e].split(" ") if len(w) > 2} - TITLES.keys()
    out = []
    for m in _WORD.finditer(text):
        w = m[0] if m[0] in parts else re.sub(r"['’]s$", "", m[0])
        if w in parts:
            out.append((m.start(), m.start() + len(w), "person"))
    return out


def entities(text: str) -> list[tuple[int, int, str]]:
    """``(start, end, type)`` of the entities of a text, left to right, not overlapping."""
    found, people = [], []
    at = 0 if _HINT.search(text) else len(text)
    while m := _RULES.search(text, at):
        real = _real(m.lastgroup, m[0])
        if real:
            found.append((*m.span(), m.lastgroup))
        at = m.end() if real else m.start() + 1
    if _NAME_HINT.search(text):
        for m in _PEOPLE.finditer(text):
            g = "titled" if m["titled"] else "named"
            words = m[g].split(" ")
            if not words[0][0].isupper():
                continue
            end = m.start(g) + (len(m[g]) if words[-1][0].isupper() else len(words[0]))
            if g == "named" and not words[-1][0].isupper():
                continue
            people.append((m.start(g), end))
    if people:
        found += [(s, e, "person") for s, e in people] + _mentions(text, people)
    out, past = [], 0
    for s, e, t in sorted(found, key=lambda x: (x[0], -x[1])):
        if s >= past:
            out.append((s, e, t))
            past = e
    return out


_FOUND = T.ArrayType(T.StructType([T.StructField("type", T.StringType()), T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType()), T.StructField("original", T.StringType()), T.StructField("surrogate", T.StringType())]))


def replace_entities(docs: DataFrame, key: str, text: str = "text", found: str = "pii") -> DataFrame:
    """``docs`` with surrogates in ``text`` and ``pii array<struct<type,start,end,original,surrogate>>``.

    ``start`` and ``end`` count characters of the original text.  Null text
    stays null with no entities.  A column named like ``found`` is replaced.
    Map-only: nothing is shuffled, whatever entity is frequent.
    """
    kind = docs.schema[text]

    def make():
        keyed = Keyed(hashlib.sha256(key.encode()).digest())
        memo: dict[tuple[str, str], str] = {}

        def fn(part):
            texts, rows = [], []
            valid = part.column(text).is_valid().to_pylist()
            for raw, there in zip(grams.texts_of(part.column(text)), valid):
                if not there:
                    texts.append(None)
                    rows.append([])
                    continue
                t = raw.decode()
                out, past, own = [], 0, []
                for s, e, what in entities(t):
                    value = t[s:e]
                    new = memo.get((what, value))
                    if new is None:
                        if len(memo) > 200_000:
                            memo.clear()
                        new = memo[what, value] = getattr(keyed, what)(value)
                    out += [t[past:s], new]
                    past = e
                    own.append({"type": what, "start": s, "end": e, "original": value, "surrogate": new})
                texts.append("".join(out) + t[past:] if own else t)
                rows.append(own)
            return [pa.array(texts, pa.string()), rows]

        return fn

    order = [c for c in docs.columns if c != found]
    return append_columns(docs, text, make, [T.StructField(text, kind.dataType), T.StructField(found, _FOUND)]).select(*order, found)


def checked(replaced: DataFrame, found: str = "pii") -> DataFrame:
    """``replaced``, written once and handed on only if no two entities share a surrogate."""
    kept = spool(replaced, "surrogates")
    bad = collisions(kept, found).take(3)
    if bad:
        raise ValueError(f"surrogates of several entities: {[tuple(r) for r in bad]}")
    return kept


def collisions(replaced: DataFrame, found: str = "pii") -> DataFrame:
    """``type, surrogate, originals`` of surrogates that stand for more than one entity."""
    each = replaced.select(F.explode(found).alias("e")).select("e.type", "e.original", "e.surrogate").distinct()
    return each.groupBy("type", "surrogate").agg(F.count("*").alias("originals")).where("originals > 1")
