"""Personal data replaced by keyed surrogates of the same type and format.

Detected: e-mail addresses, phone numbers, IPv4 addresses, card-like numbers, and names:
after a title, after words that introduce one ("my name is"), or from the name lists, to
which callers add their own. Once a text names somebody, the same words elsewhere in
that text are names too. Other names are not told from other capitalised words.

A surrogate is the entity's successor in a keyed order of all strings of its form:
digits stay digits, letters keep their script, in names vowels stay vowels and
consonants consonants, and punctuation and case are put back. So no two entities share
a surrogate, none is its own, and the same entity has the same one everywhere, in any
task, without a table. The order is walked on to the next string that is of the same
kind: a card number keeps whether its checksum holds, an address stays an address, a
name from a list (script and gender) goes to its list and any other never does. Gender
follows the list, else the title, which stays as it is. ``collisions`` audits it.

Defined results: a null text stays null; texts without entities are unchanged to the
byte; overlapping finds go to the first kind in KINDS; an e-mail address is the same
entity in any case; rows are independent, other columns stay, empty tables are fine.
The key has 16 bytes at least and no default.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import need, prepare

KINDS = ("email", "ip", "phone", "card", "name")
# Titles by gender, and given names by script and gender.
TITLES = {"f": ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Señora", "Sra", "Госпожа"), "m": ("Mr", "Herr", "Monsieur", "Señor", "Sr", "Господин"), "": ("Dr", "Prof")}
NAMES = {
    ("latin", "f"): ("Anna", "Maria", "Elena", "Julia", "Laura", "Sofia", "Clara", "Emma", "Nina", "Alice", "Marta", "Lucia", "Irene", "Paula", "Sarah", "Helen"),
    ("latin", "m"): ("John", "Peter", "Thomas", "David", "Daniel", "Michael", "Robert", "Carlos", "Pablo", "Pierre", "Louis", "Hans", "Karl", "Martin", "James", "Paul"),
    ("cyrillic", "f"): ("Анна", "Мария", "Елена", "Ольга", "Ирина", "Наталья", "Татьяна", "Светлана"),
    ("cyrillic", "m"): ("Иван", "Пётр", "Сергей", "Алексей", "Дмитрий", "Николай", "Андрей", "Михаил"),
}
ALPHABETS = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "àáâãäåçèéêëìíîïñòóôõöùúûüýÿ", "абвгдежзийклмнопрстуфхцчшщъыьэюяё", "αβγδεζηθικλμνξοπρστυφχψω")
VOWELS = "aeiouyàáâãäåèéêëìíîïòóôõöùúûüýÿаеёиоуыэюяαεηιουω"
#: Words that introduce a name, whether it is one word or more, and only if it is two or more.
CUES = ("[Mm]y name is", "[Nn]ame:", "[Ii]ch heiße", "[Mm]ein Name ist", "[Jj]e m'appelle", "[Mm]e llamo", "[Mm]i nombre es", "[Мм]еня зовут")
CUES_FULL = ("[Dd]ear", "[Cc]ontact:?", "[Ss]igned(?: by)?:?", "[Rr]egards,", "[Ss]incerely,", "[Ll]iebe[r]?", "[Cc]her|[Cc]hère", "[Ee]stimad[oa]")
_TITLE = "|".join(sorted((t for v in TITLES.values() for t in v), key=len, reverse=True))
_CAPITAL = r"[A-ZÀ-ÖØ-ÞА-ЯЁ]\w+"
PATTERNS = {
    "email": r"[^\W_][\w.%+-]*@[^\W_][\w-]*(?:\.[^\W_][\w-]*)+",
    "ip": r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|[01]?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|[01]?\d?\d)(?!\.?\d)",
    "phone": r"(?<![\w+])(?:\+\d{1,3}[ .-]?(?:\(\d{2,4}\)|\d{2,4})(?:[ .-]?\d{2,4}){2,3}|(?:\(\d{3}\) ?|\d{3}[.-])\d{3}[.-]\d{4})(?!\d)",
    "card": r"(?<![\d+])\d(?:[ -]?\d){12,18}(?!\d)",
}
LEAST_KEY = 16


@lru_cache(maxsize=4)
def _listed(more: tuple[str, ...]) -> str:
    return "|".join([*(n for v in NAMES.values() for n in v), *map(re.escape, more)])


def hint(more: tuple[str, ...] = ()) -> str:
    """What a text must hold for any pattern to match; runs in the JVM and spares most texts the way to Python."""
    cues = "|".join((*CUES, *CUES_FULL))
    return rf"@|[0-9]\.[0-9]|[0-9][ .-]?[0-9]{{2}}|\b(?:{_TITLE})\.? \p{{Lu}}|\b(?:{_listed(more)})\b|\b(?:{cues})\s+\p{{Lu}}"


def _number(key: bytes, *parts: object) -> int:
    return int.from_bytes(hashlib.blake2b(repr(parts).encode(), key=key, digest_size=32).digest(), "big")


def _mixed(digits: list[int], sizes: list[int], key: bytes, tweak: object, back: bool = False) -> list[int]:
    """A keyed bijection of digit lists, or its inverse; digit i ranges over sizes[i]. Balanced Feistel over the two halves."""
    n = len(digits)
    if n == 1:
        order = _order(sizes[0], key, repr(tweak))
        return [order[digits[0]] if back else order.index(digits[0])]
    half = n // 2
    a, b = digits[:half], digits[half:]
    for r in reversed(range(8)) if back else range(8):
        source, target, size = (b, a, sizes[:half]) if r % 2 == 0 else (a, b, sizes[half:])
        whole = 1
        for s in size:
            whole *= s
        value = 0
        for d, s in zip(target, size):
            value = value * s + d
        move = _number(key, tweak, r, source)
        value = (value - move if back else value + move) % whole
        for i in range(len(target) - 1, -1, -1):
            value, target[i] = divmod(value, size[i])
    return a + b


@lru_cache(maxsize=256)
def _order(size: int, key: bytes, tweak: str) -> list[int]:
    return sorted(range(size), key=lambda x: _number(key, tweak, x))


def successors(digits: list[int], sizes: list[int], key: bytes, tweak: object):
    """All other digit lists in a keyed order, from the one after ``digits`` on: one cycle through all of them."""
    at = _mixed(digits, sizes, key, tweak)
    while True:
        for i in reversed(range(len(at))):
            at[i] = (at[i] + 1) % sizes[i]
            if at[i]:
                break
        yield _mixed(list(at), sizes, key, tweak, back=True)


_CLASS = {c: (k, i, len(letters)) for k, letters in enumerate(ALPHABETS) for i, c in enumerate(letters)}
_SOUND: dict[str, tuple[int, int, int]] = {}
for _k, _letters in enumerate(ALPHABETS):
    for _v in (True, False):
        _own = [c for c in _letters if (c in VOWELS) == _v]
        _SOUND |= {c: (2 * _k + _v, i, len(_own)) for i, c in enumerate(_own)}


@lru_cache(maxsize=64)
def _page(number: int) -> tuple[dict[str, int], list[str]]:
    """Letters and digits of a stretch of 256 code points."""
    own = [c for c in map(chr, range(number << 8, (number + 1) << 8)) if c.isalnum() and c.lower() == c]
    return {c: i for i, c in enumerate(own)}, own


def _place(c: str, table: dict) -> tuple[int, int, int] | None:
    """(class, place in it, its size) of a character; scripts without an alphabet here have their code page."""
    if c in table:
        return table[c]
    if c < "\x80" or not c.isalnum():
        return None
    places, own = _page(ord(c) >> 8)
    left = [x for x in own if x not in table]
    return (1000 + (ord(c) >> 8), left.index(c), len(left)) if c in places else None


def formatted(text: str, key: bytes, kind: str, fits=lambda new: True) -> str:
    """The next string over the text's skeleton that ``fits``; case is put back."""
    table = _SOUND if kind == "name" else _CLASS
    low = [c.lower() if len(c.lower()) == 1 else c for c in text]
    spot = {i: p for i, c in enumerate(low) if (p := _place(c, table)) is not None}
    if not spot:
        return text
    skeleton = "".join(f"{spot[i][0]}." if i in spot else c for i, c in enumerate(low))
    letters = {k: {j: c for c, (a, j, _) in table.items() if a == k} for k in {p[0] for p in spot.values()} if k < 1000}
    pages = {k: [x for x in _page(k - 1000)[1] if x not in table] for k in {p[0] for p in spot.values()} if k >= 1000}
    start = [p[1] for p in spot.values()]
    for new in successors(start, [p[2] for p in spot.values()], key, (kind, skeleton)):
        out = list(low)
        for i, d in zip(spot, new):
            c = (letters.get(spot[i][0]) or pages[spot[i][0]])[d]
            out[i] = c.upper() if text[i] != text[i].lower() and len(c.upper()) == 1 else c
        if new == start or fits("".join(out)):
            return "".join(out)
    raise AssertionError


def checksum(text: str) -> bool:
    """Whether the digits end in the check digit that payment cards have."""
    digits = [int(c) for c in reversed(text) if c.isdigit()]
    return sum(d if i % 2 == 0 else d * 2 - 9 * (d > 4) for i, d in enumerate(digits)) % 10 == 0


def _plain(text: str) -> bool:
    """An address written without leading zeros."""
    return all(str(int(x)) == x for x in text.split("."))


def _ip(text: str, key: bytes) -> str:
    if _plain(text):
        return ".".join(map(str, next(successors([int(x) for x in text.split(".")], [256] * 4, key, "ip"))))
    return formatted(text, key, "ip", lambda new: not _plain(new) and all(int(x) < 256 for x in new.split(".")))


@lru_cache(maxsize=8)
def _lists(key: bytes, more: tuple[str, ...] = ()) -> dict[str, str]:
    """Each listed name's surrogate: the next in its list's keyed order."""
    out = {}
    for group, names in {**NAMES, "more": more}.items():
        order = sorted(set(names) - set(out), key=lambda n: _number(key, group, n))
        out |= {n: order[(i + 1) % len(order)] for i, n in enumerate(order)}
    return out


def _name(text: str, key: bytes, more: tuple[str, ...] = ()) -> str:
    listed = _lists(key, more)
    return " ".join(listed[w] if w in listed else formatted(w, key, "name", lambda new: new not in listed) for w in text.split(" "))


def surrogate(kind: str, text: str, key: bytes, more: tuple[str, ...] = ()) -> str:
    if kind == "card":
        return formatted(text, key, kind, lambda new: checksum(new) == checksum(text))
    if kind == "email":
        name, _, rest = text.rpartition("@")
        host, _, top = rest.rpartition(".")
        return formatted(f"{name}@{host}", key, "email") + "." + top
    if kind == "ip":
        return _ip(text, key)
    if kind == "phone" and text[0] == "+":
        code = re.match(r"\+\d{1,3}(?=\D)", text)
        keep = code.end() if code else 1
        return text[:keep] + formatted(text[keep:], key, text[:keep])
    return _name(text, key, more) if kind == "name" else formatted(text, key, kind)


@lru_cache(maxsize=4)
def _finders(more: tuple[str, ...]) -> list[tuple[str, re.Pattern]]:
    listed = rf"\b(?P<listed>(?:{_listed(more)})(?: {_CAPITAL})?)\b"
    name = rf"\b(?:{_TITLE})\.? (?P<titled>{_CAPITAL}(?: {_CAPITAL})?)|{listed}|\b(?:{'|'.join(CUES)})\s+(?P<cued>{_CAPITAL}(?: {_CAPITAL}){{0,2}})|\b(?:{'|'.join(CUES_FULL)})\s+(?P<full>{_CAPITAL}(?: {_CAPITAL}){{1,2}})"
    return [(k, re.compile(PATTERNS[k] if k in PATTERNS else name)) for k in KINDS]


def entities(text: str, more: tuple[str, ...] = ()) -> list[tuple[int, int, str, str]]:
    """(start, end, kind, entity) in order, none overlapping."""
    out: list[tuple[int, int, str, str]] = []

    def add(kind: str, spans) -> None:
        # Both in order: each span is held against the neighbour it falls before.
        held = sorted(out)
        starts = [x[0] for x in held]
        for a, b in spans:
            k = bisect(starts, a)
            if (k == 0 or held[k - 1][1] <= a) and (k == len(held) or b <= starts[k]):
                out.append((a, b, kind, text[a:b]))

    for kind, finder in _finders(more):
        add(kind, [m.span(m.lastgroup if kind == "name" else 0) for m in finder.finditer(text)])
    # Whoever has been named is named again by part of the name.
    parts = {w for *_, kind, name in out if kind == "name" for w in name.split(" ") if len(w) > 2}
    if parts:
        add("name", [m.span() for m in re.finditer(rf"\b(?:{'|'.join(sorted(map(re.escape, parts)))})\b", text)])
    return sorted(out)


def replaced(text: str, key: bytes, more: tuple[str, ...] = ()) -> tuple[str, list[str]]:
    parts, at, kinds = [], 0, []
    for a, b, kind, entity in entities(text, more):
        parts += [text[at:a], surrogate(kind, entity, key, more)]
        at = b
        kinds.append(kind)
    return "".join([*parts, text[at:]]) if kinds else text, kinds


def _checked(key: bytes) -> bytes:
    if not isinstance(key, bytes) or len(key) < LEAST_KEY:
        raise ValueError(f"a key of {LEAST_KEY} bytes at least is needed")
    return key[:64] if len(key) > 64 else key


def _udf(key: bytes, more: tuple[str, ...]):
    result = "struct<text: string, kinds: array<string>>"
    kind = pa.struct([("text", pa.string()), ("kinds", pa.list_(pa.string()))])

    @F.arrow_udf(result)
    def work(column: pa.Array) -> pa.Array:
        return pa.array([None if t is None else dict(zip(("text", "kinds"), replaced(t, key, more))) for t in column.to_pylist()], kind)

    return work


def pseudonymise(docs: DataFrame, key: bytes, column: str = "text", into: str = "kinds", names: tuple[str, ...] = ()) -> DataFrame:
    """``docs`` with surrogates in ``column`` and the kinds of what was replaced, in order, in array ``into``.

    ``names``: given names beside the listed ones; they stand for one another. Whoever has
    the key can find out what was replaced, so it is the caller's to keep.
    """
    need(docs, column)
    prepare(docs.sparkSession)
    text = F.col(column).cast("string")
    got = F.struct(_udf(_checked(key), tuple(names))(F.when(text.rlike(hint(tuple(names))), text)).alias("new"), text.alias("old"))
    # One struct under the name of an output, so that no other column of docs can clash.
    both = docs.withColumn(into, got)
    return both.withColumns({column: F.coalesce(F.col(f"`{into}`.new.text"), F.col(f"`{into}`.old")), into: F.coalesce(F.col(f"`{into}`.new.kinds"), F.array().cast("array<string>"))})


def found(docs: DataFrame, key: bytes, column: str = "text", names: tuple[str, ...] = ()) -> DataFrame:
    """(kind, entity, surrogate) of every entity of every text."""
    prepare(docs.sparkSession)
    key, more = _checked(key), tuple(names)
    item = pa.list_(pa.struct([("kind", pa.string()), ("entity", pa.string()), ("surrogate", pa.string())]))

    def one(kind: str, entity: str) -> dict:
        new = surrogate(kind, entity, key, more)
        if kind == "email":
            entity, new = entity.lower(), new.lower()
        return {"kind": kind, "entity": entity, "surrogate": new}

    @F.arrow_udf("array<struct<kind: string, entity: string, surrogate: string>>")
    def listed(texts: pa.Array) -> pa.Array:
        return pa.array([[one(k, e) for *_, k, e in entities(t or "", more)] for t in texts.to_pylist()], item)

    text: Column = F.col(column).cast("string")
    return docs.where(text.rlike(hint(more))).select(F.explode(listed(text)).alias("x")).select("x.*")


def collisions(pairs: DataFrame) -> DataFrame:
    """Surrogates that stand for several entities, and entities with several surrogates: none are expected."""
    one = pairs.groupBy("kind", "entity", "surrogate").agg(F.count(F.lit(1)).alias("n"))
    by = one.groupBy("kind", "surrogate").agg(F.count(F.lit(1)).alias("sides"), F.min("entity").alias("example"))
    back = one.groupBy("kind", "entity").agg(F.count(F.lit(1)).alias("sides"), F.min("surrogate").alias("example"))
    return by.where("sides > 1").select("kind", F.col("surrogate").alias("value"), "sides", "example").unionByName(back.where("sides > 1").select("kind", F.col("entity").alias("value"), "sides", "example"))
