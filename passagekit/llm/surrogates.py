"""PII surrogates: detected entities are replaced by keyed, type-consistent stand-ins.

An entity is first brought to a normal form (separators aside; letter case too for mail addresses and names), the form is replaced by a
keyed one-to-one map, and the result is written in the format of the original: separators, checked prefixes, case of letters, number of
words, titles. So an entity has the same surrogate in every text and in every format, and no two entities of a type share one, over the
whole corpus and without any table:

* the variable characters of a patterned entity (mail and network addresses, telephone, card, account and social security numbers,
  secrets) are one number in a mixed radix (digits, letters by case and script, hexadecimal digits); a Feistel permutation with cycle walking, a keyed step
  and the inverse permutation map it to another number of the same range. Valid card numbers go to valid ones, others to others;
* each word of a person's name (after a title) is a number too, in the alphabet of its script; permuted among all words of its length it is spelled in
  syllables of that script. First names end by gender (as the title says), last names do not, so "Mr John Smith" and "Mr Smith" stay one family.

A collision check keeps a surrogate from being a name or number that the same text holds in the original: it gets another one (numbers
step on round the circle until one is free in the text; a name takes a syllable that is kept for this, so no other name has it). Only there may texts differ.

Null texts stay null and have no entities; texts without entities stay as they are; repeated rows give repeated results;
an empty table gives an empty result; columns other than id and text pass through `replace` unread. Long texts are
read whole.
"""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

KEY = b"surrogate-key-1"

# Titles before names, by gender.
_FEMALE = ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Lady", "Señora", "Sra", "Doña", "Госпожа", "г-жа", "Κυρία")
_MALE = ("Mr", "Herr", "Monsieur", "Sir", "Lord", "Señor", "Sr", "Don", "Господин", "г-н", "Κύριος")
_NEUTRAL = ("Dr", "Prof", "Professor")
#: A name: a capital and letters, in parts with hyphens or apostrophes.
_CAPITAL, _PART = r"[^\W\d_a-zß-öø-ÿа-яёα-ωά-ώ]", r"[^\W\d_]"
_NAME = rf"(?:{_CAPITAL}['’])?{_CAPITAL}{_PART}+(?:[-'’]{_PART}+)*"
_TITLES = "|".join((*_FEMALE, *_MALE, *_NEUTRAL))
#: Initials, particles and second titles between a title and a name; they stay as they are.
_BEFORE = rf"(?:(?:{'|'.join(_NEUTRAL)})\.? |{_CAPITAL}(?:\. ?| )|(?:van|von|der|den|de|del|della|di|da|dos|du|la|las|los|le|zu|zum|zur|ten|ter|bin|al|el) ){{0,4}}"
_OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
# What counts as an entity, by type; earlier types win where matches begin together.
PATTERNS = {
    "email": r"[\w.+-]*\w@\w[\w-]*(?:\.\w[\w-]*)+",
    "secret": r"(?i:\b(?:token|password|passwd|secret|api[_-]?key)\b\s*[=:]\s*[\"']?)(?P<secret_value>[^\s\"']{6,})|\bAKIA[0-9A-Z]{16}\b|\bgh[pousr]_[A-Za-z0-9]{36}\b",
    "ip": rf"(?<![\d.])(?:{_OCTET}\.){{3}}{_OCTET}(?!\d)(?!\.\d)",
    "phone": r"(?<![\w+])\+\d{1,3}[ .-]?\(?\d{2,4}\)?(?:[ .-]?\d{2,4}){1,4}(?!\d)|(?<![\w(])\(\d{3}\) ?\d{3}[ .-]\d{4}(?!\d)|(?<![\d-])\d{3}[.-]\d{3}[.-]\d{4}(?![\d-])",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "card": r"(?<![\d.])\d(?:[ -]?\d){12,18}(?!\d)",
    "iban": r"\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b",
    "person": rf"\b(?P<title>{_TITLES})\.? {_BEFORE}(?P<name>{_NAME}(?: (?!(?:{_TITLES})\b){_NAME}){{0,2}})",
}
_ALL = re.compile("|".join(f"(?P<{k}>{v})" for k, v in PATTERNS.items()))
# No entity is without one of these: every match of PATTERNS holds a title and what follows it, an at sign or what _MARKS finds.
_TITLED = [t + end for t in _TITLES.split("|") for end in (" ", ". ")]
#: The beginnings of all titles, those beyond ASCII apart.
_STEMS = sorted({t for t in _TITLES.split("|") if not any(t != u and t.startswith(u) for u in _TITLES.split("|"))})
_ASCII, _WIDE = [t for t in _STEMS if t.isascii()], [t for t in _STEMS if not t.isascii()]
_MARKS = re.compile(r"[\d=:Ag](?:(?<=\d)(?:[\d ().-]{6}|\.\d|(?<=\+\d)|\d(?<=[A-Z]{2}\d\d))|(?<=[=:])\s*[\"']?\S{6}|(?<=A)KIA|(?<=g)h[pousr]_)")


def may_hold(text: str) -> bool:
    """False only for texts without an entity."""
    if "@" in text or _MARKS.search(text):
        return True
    stem = any(t in text for t in _ASCII) or not text.isascii() and any(t in text for t in _WIDE)
    return stem and any(t in text for t in _TITLED)


_CLASSES = ["0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "абвгдежзийклмнопрстуфхцчшщъыьэюя", "АБВГДЕЖЗИЙКЛМНОПРСТУФХЦЧШЩЪЫЬЭЮЯ", "αβγδεζηθικλμνξοπρστυφχψω", "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ"]
_CLASS = {c: k for k, cs in enumerate(_CLASSES) for c in cs}
_HEX = "0123456789abcdef"
# By script, the letters of names, consonants and vowels of syllables, consonants kept for the collision check, and the ends of
# first names by gender.
_SCRIPTS = {
    "latin": ("abcdefghijklmnopqrstuvwxyz", "bdfgklmnprstvz", "aeiou", "w", {"f": "a", "m": "n", "n": "i"}),
    "cyrillic": ("абвгдеёжзийклмнопрстуфхцчшщъыьэюя", "бвгдзклмнпрстф", "аеиоу", "х", {"f": "а", "m": "н", "n": "и"}),
    "greek": ("αβγδεζηθικλμνξοπρσςτυφχψωάέήίόύώϊϋΐΰ", "βγδζθκλμνπρστφ", "αεηιο", "χ", {"f": "α", "m": "ς", "n": "ι"}),
}


def _digest(key: bytes, *parts) -> int:
    return int.from_bytes(hashlib.blake2b("\x1f".join(map(str, parts)).encode("utf-8", "surrogatepass"), key=key, digest_size=32).digest(), "big")


def permute(x: int, n: int, key: bytes, tweak: str) -> int:
    """A keyed permutation of 0..n-1: eight Feistel rounds on enough bits, walked until the result is below n."""
    half = max(1, ((n - 1).bit_length() + 1) // 2)
    mask = (1 << half) - 1
    while True:
        left, right = x >> half, x & mask
        for i in range(8):
            left, right = right, left ^ (_round(right, half, key, tweak, i) & mask)
        x = left << half | right
        if x < n:
            return x


def unpermute(y: int, n: int, key: bytes, tweak: str) -> int:
    """The inverse of permute."""
    half = max(1, ((n - 1).bit_length() + 1) // 2)
    mask = (1 << half) - 1
    while True:
        left, right = y >> half, y & mask
        for i in reversed(range(8)):
            left, right = right ^ (_round(left, half, key, tweak, i) & mask), left
        y = left << half | right
        if y < n:
            return y


def _round(x: int, half: int, key: bytes, tweak: str, i: int) -> int:
    f, need = 0, half
    while need > 0:
        f, need = f << 256 | _digest(key, tweak, i, x, need), need - 256
    return f


def moved(x: int, n: int, key: bytes, tweak: str, hop: int = 1) -> int:
    """A keyed one-to-one map of 0..n-1 that leaves no number where it is (n > 1): a step round a keyed circle. hop: times the step is taken."""
    if n < 2:
        return x
    step = 1 + _digest(key, "step", tweak) % (n - 1)
    return unpermute((permute(x, n, key, tweak) + step * hop) % n, n, key, tweak)


def _mixed(chars: list[str], sets: list[str], key: bytes, tweak: str, hop: int = 1) -> list[str]:
    x, n = 0, 1
    for c, s in zip(chars, sets, strict=True):
        x, n = x * len(s) + s.index(c), n * len(s)
    x, out = moved(x, n, key, tweak, hop), []
    for s in reversed(sets):
        x, r = divmod(x, len(s))
        out.append(s[r])
    return out[::-1]


def keep_format(value: str, key: bytes, kind: str, fixed: int = 0, hop: int = 1) -> str:
    """value with its letters and digits changed within their classes; the first `fixed` characters stay, and separators do not matter."""
    is_hex = kind == "secret" and len(value) - fixed >= 16 and set(value[fixed:]) <= set(_HEX) and not value[fixed:].isdigit()
    at, sets = [], []
    for i, c in enumerate(value):
        s = None if i < fixed else _HEX if is_hex else _CLASSES[_CLASS[c]] if c in _CLASS else None
        if s is not None:
            at.append(i)
            sets.append(s)
    out = list(value)
    for i, c in zip(at, _mixed([value[i] for i in at], sets, key, f"{kind}|{''.join(str(len(s)) + s[0] for s in sets)}", hop), strict=True):
        out[i] = c
    return "".join(out)


def luhn(digits: str) -> int:
    """The check digit that follows digits."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (2 - i % 2)
        total += d - 9 * (d > 9)
    return -total % 10


def _card(value: str, key: bytes, hop: int = 1) -> str:
    digits = re.sub(r"\D", "", value)
    if luhn(digits[:-1]) == int(digits[-1]):
        own = keep_format(digits[:-1], key, "card", 0, hop)
        own += str(luhn(own))
    else:  # walk on until the check digit is wrong again, so both kinds stay apart
        own = digits
        for _ in range(hop):
            own = keep_format(own, key, "number")
            while luhn(own[:-1]) == int(own[-1]):
                own = keep_format(own, key, "number")
    left = iter(own)
    return "".join(next(left) if c.isdigit() else c for c in value)


def _ip(value: str, key: bytes, hop: int = 1) -> str:
    x = 0
    for part in value.split("."):
        x = x << 8 | int(part)
    y = moved(x, 1 << 32, key, "ip", hop)
    return ".".join(str(y >> s & 255) for s in (24, 16, 8, 0))


def _email(value: str, key: bytes, hop: int = 1) -> str:
    local, domain = value.rsplit("@", 1)
    host, dot, top = domain.rpartition(".")
    old = f"{local}@{host}"
    new = keep_format(old.lower() if len(old.lower()) == len(old) else old, key, "email", 0, hop)
    return "".join(n.upper() if o.isupper() and len(n.upper()) == 1 else n for o, n in zip(old, new, strict=True)) + dot + top


def script_of(name: str) -> str:
    c = next((c for c in name if c.isalpha()), "a")
    return "cyrillic" if "\u0400" <= c <= "\u052f" else "greek" if "\u0370" <= c <= "\u03ff" or "\u1f00" <= c <= "\u1fff" else "latin"


def _number(word: str, letters: str) -> int:
    """The place of a word of letters among all words, the shorter first."""
    x = 0
    for c in word:
        x = x * len(letters) + letters.index(c) + 1
    return x


def name_word(word: str, gender: str | None, key: bytes, apart: bool = False) -> str:
    """The surrogate of one word of a name, lower case; gender is None for last names. One-to-one for each role; `apart` gives one that no word has otherwise."""
    script = script_of(word)
    letters, onsets, vowels, kept, ends = _SCRIPTS[script]
    low = word.lower()
    plain = set(low) <= set(letters)
    if not plain:  # letters beyond the alphabet: spelled by their code points, and marked
        letters = "0123456789abcdef."
        low = ".".join(f"{ord(c):x}" for c in low)
    size = len(letters)
    first = sum(size**k for k in range(1, len(low)))  # words that are shorter
    x = first + moved(_number(low, letters) - 1 - first, size ** len(low), key, f"name {script} {plain} {gender} {len(low)}")
    syllables, out = [c + v for c in onsets for v in vowels], []
    x += len(syllables)  # two syllables at least
    while x >= 0:
        x, r = divmod(x, len(syllables))
        out.append(syllables[r])
        x -= 1
    # marks are of a consonant that no syllable has
    mark = "" if plain else kept + vowels[0]
    return mark + "".join(out) + (kept + vowels[1] if apart else "") + (ends[gender] if gender else "")


def person(name: str, gender: str, key: bytes, apart: bool = False) -> str:
    """A name of as many words and parts, in the same script and case."""
    words = name.split(" ")
    out = []
    for i, w in enumerate(words):
        role = gender if i < len(words) - 1 else None
        out.append(re.sub(r"[^\W\d_]+", lambda m, role=role: _cased(m[0], name_word(m[0], role, key, apart)) if len(m[0]) > 1 else m[0], w))
    return " ".join(out)


def _cased(old: str, new: str) -> str:
    return new.upper() if old.isupper() and len(old) > 1 else new[0].upper() + new[1:] if old[0].isupper() else new


class Surrogates:
    """Replaces the entities of texts under one key."""

    def __init__(self, key: bytes = KEY):
        self.key, self.known = key, {}

    def of(self, kind: str, value: str, hop: int = 1) -> str:
        got = self.known.get((kind, value, hop))
        if got is None:
            if len(self.known) > 100_000:
                self.known.clear()
            if kind == "email":
                got = _email(value, self.key, hop)
            elif kind == "ip":
                got = _ip(value, self.key, hop)
            elif kind == "card":
                got = _card(value, self.key, hop)
            elif kind == "phone":
                got = keep_format(value, self.key, kind, len(re.match(r"\+\d{1,3}(?=[ .(-])|", value)[0]), hop)
            elif kind == "secret":
                got = keep_format(value, self.key, kind, 4 if re.match(r"AKIA|gh[pousr]_", value) else 0, hop)
            else:
                got = keep_format(value, self.key, kind, 2 if kind == "iban" else 0, hop)
            self.known[kind, value, hop] = got
        return got

    def named(self, name: str, gender: str, apart: bool) -> str:
        got = self.known.get((gender, name, apart))
        if got is None:
            if len(self.known) > 100_000:
                self.known.clear()
            got = self.known[gender, name, apart] = person(name, gender, self.key, apart)
        return got

    def replace(self, text: str | None) -> tuple[str | None, list[tuple[str, int, int]]]:
        """(text with surrogates, entities found as type, start and end in the original)."""
        if not text or not may_hold(text):
            return text, []
        spans = []
        for m in _ALL.finditer(text):
            kind = m.lastgroup if m.lastgroup in PATTERNS else next(k for k in PATTERNS if m[k] is not None)
            group = "name" if kind == "person" else "secret_value" if m["secret_value"] is not None else kind
            spans.append((kind, *m.span(group), m["title"]))
        moves = self._moves({(kind, text[a:b]) for kind, a, b, _ in spans if kind != "person"})
        words = {w for kind, a, b, _ in spans if kind == "person" for w in re.findall(r"[^\W\d_]+", text[a:b].lower())}
        found, out, at = [], [], 0
        for kind, start, end, title in spans:
            value = text[start:end]
            if kind == "person":
                gender = "f" if title in _FEMALE else "m" if title in _MALE else "n"
                new = self.named(value, gender, False)
                if not words.isdisjoint(re.findall(r"[^\W\d_]+", new.lower())):
                    new = self.named(value, gender, True)
            else:
                new = self.of(kind, value, moves.get((kind, _normal(value)), 1))
            found.append((kind, start, end))
            out += [text[at:start], new]
            at = end
        return "".join(out) + text[at:], found

    def _moves(self, entities: set[tuple[str, str]]) -> dict[tuple[str, str], int]:
        """Steps for the entities whose first surrogate is an original of the text: the first that neither are nor are first surrogates of others."""
        originals = {_normal(v) for _, v in entities}
        own = {(k, _normal(v)): self.of(k, v) for k, v in sorted(entities)}
        taken, out = originals | {_normal(v) for v in own.values()}, {}
        for kind, value in sorted(entities):
            at = kind, _normal(value)
            if at not in out and _normal(own[at]) in originals:
                for hop in range(2, 2 * len(entities) + 4):  # a range that is used up keeps its first surrogate
                    new = _normal(self.of(kind, value, hop))
                    if new not in taken:
                        out[at] = hop
                        taken.add(new)
                        break
        return out


def _normal(value: str) -> str:
    return re.sub(r"[\W_]", "", value).lower()


def replace(docs: DataFrame, key: bytes = KEY, id_col: str = "doc_id", text_col: str = "text", spans: bool = True) -> DataFrame:
    """docs with surrogates in text_col; spans adds `entities` (type, start and end of each in the original).

    An input column called entities is replaced by the new one.
    """
    docs = docs.drop("entities") if spans else docs
    names = docs.columns
    at = names.index(text_col)
    fields = ", ".join(f"`{n}` {t}" for n, t in docs.dtypes) + (", entities array<struct<kind:string,start:int,end:int>>" if spans else "")

    def run(it):
        import pyarrow as pa

        own = Surrogates(key)
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        for batch in slices(it):
            done = [own.replace(t) for t in batch.column(at).to_pylist()]
            cols = batch.columns
            cols[at] = pa.array([t for t, _ in done], pa.string())
            if spans:
                cols = [*cols, pa.array([[{"kind": k, "start": a, "end": b} for k, a, b in e] for _, e in done], kind)]
            yield pa.RecordBatch.from_arrays(cols, names=[*names, *["entities"] * spans])

    return docs.mapInArrow(run, fields)


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    out = replace(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "text", F.size("entities").cast("long").alias("n_entities"), F.array_join(F.array_sort(F.array_distinct(F.transform("entities", lambda e: e["kind"]))), ",").alias("kinds"))
