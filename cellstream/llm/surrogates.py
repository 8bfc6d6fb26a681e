"""Surrogate generation for personal data: keyed, type-consistent, distinct by construction and checked over the corpus.

Entities (e-mail, IBAN, card or account number, phone, social security number, IP address, credential, person) are found by one
pattern, and later or earlier mentions of a person's names by a table of the document's own persons. A surrogate is a keyed
permutation without fixed points of the strings of the same type and format: letters stay letters of their script and
case (vowels vowels, consonants consonants where a script tells them apart), digits digits, and separators, titles, country codes,
top-level domains, address class and check digits' validity stay. So no entity stays as it is, equal entities get
equal surrogates, and different entities different ones, in every task and without any exchange.

Coreference: an entity's identity is its value without formatting (blanks of an IBAN or card, case of an e-mail), so all its
spellings get one surrogate, written in each one's format. The words of a person are replaced by their role, given or family name, and not
by their place, so "Mr John Smith", "Mr Smith", "John Smith" and "Smith" of one document agree. Given names of a known
gender are swapped within a pool of that gender; others keep script and length and take an ending of the title's gender, where the
script has one. ``pseudonymised`` counts collisions over the corpus and raises if there is any.

Null text stays null with no entities; empty and very long texts are treated whole; rows, repeated ones too, and other
columns are kept, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

import hmac
import re
import unicodedata

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

# Titles by gender (n: either), and given names that are swapped within their gender.
TITLES = {
    "m": ["Mr", "Herr", "Monsieur", "Señor", "Sir", "Mister", "Sr", "Господин", "Κύριος"],
    "f": ["Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Mademoiselle", "Señora", "Señorita", "Sra", "Madam", "Lady", "Госпожа", "Κυρία"],
    "n": ["Dr", "Prof", "Professor", "Mx"],
}
NAMES = {
    "m": ["James", "John", "Robert", "Michael", "William", "David", "Richard", "Thomas", "Charles", "Daniel", "Matthew", "Anthony", "Mark", "Paul", "Steven", "George", "Hans", "Karl", "Pierre", "Jean", "Carlos", "Juan"],
    "f": ["Mary", "Patricia", "Jennifer", "Linda", "Elizabeth", "Barbara", "Susan", "Jessica", "Sarah", "Karen", "Nancy", "Lisa", "Margaret", "Sandra", "Ashley", "Emily", "Jane", "Anna", "Marie", "Claire", "Carmen", "Ingrid"],
}
# Vowels of the scripts that tell them apart by letter, and endings of given names by gender. No ending is the end of another
# or of a name above, so a name with its ending has one origin.
VOWELS = {"LATIN": "aeiou", "GREEK": "αεηιουω", "CYRILLIC": "аеиоуыэюя"}
ENDINGS = {"LATIN": {"m": "andro", "f": "ella", "n": "im"}, "GREEK": {"m": "ος", "f": "ουλα", "n": "ι"}, "CYRILLIC": {"m": "ий", "f": "ая", "n": "ко"}}
# Calling codes of one and two digits; all others have three.
CALLING = {"1", "7", *"20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split()}

_GENDER = {t: g for g, ts in TITLES.items() for t in ts}
_TITLE = "|".join(sorted(_GENDER, key=len, reverse=True))
_NAME = r"[^\W\d_](?:[^\W\d_]|[\-'’](?=[^\W\d_]))*"
ENTITY = re.compile(
    r"(?P<email>(?<![\w.+-])[\w.+-]+@[\w-]+(?:\.[\w-]+)+)"
    r"|(?i:\b(?:token|secret|passw(?:or)?d|api[_-]?key)\b[\"']?\s*[=:]\s*[\"']?)(?P<credential>[A-Za-z0-9_\-+/]{12,})"
    r"|(?P<ip>(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\d]|\.\d))"
    r"|(?P<ssn>(?<!\d)\d{3}-\d{2}-\d{4}(?!\d))"
    r"|(?P<iban>(?<!\w)[A-Z]{2}\d{2}(?:[A-Z0-9]{11,30}|(?: [A-Z0-9]{4}){2,7}(?: [A-Z0-9]{1,3})?)(?!\w))"
    r"|(?P<card>(?<![\d.])(?:\d{13,19}|\d{4}(?:[ -]\d{4}){3})(?!\d))"
    r"|(?P<phone>(?<![\w.])(?:\+\d{1,3}(?:[ .\-/]?\(?\d{1,4}\)?){2,5}|(?:\(\d{2,4}\)[ .-]?|\d{2,4}[ .-])\d{3,4}[ .-]\d{3,4})(?!\d))"
    rf"|\b(?P<title>{_TITLE})\b\.? (?P<person>{_NAME}(?: {_NAME}){{0,2}})"
)
# Some match of this is in every text with an entity: each alternative above needs a digit, an at sign, a cue word or a title.
_WORTH = re.compile(r"[@\d]|(?i:token|secret|passw|api[_-]?key)|" + rf"\b(?:{_TITLE})\b")


def _feistel(value: int, half: int, key: bytes, tweak: bytes, rounds) -> int:
    mask, width = (1 << half) - 1, half // 8 + 1
    left, right = value >> half, value & mask
    for k in rounds:
        digest = b"".join(hmac.digest(key, tweak + bytes([k, n]) + right.to_bytes(width, "big"), "sha256") for n in range(width // 32 + 1))
        left, right = right, left ^ int.from_bytes(digest[:width], "big") & mask
    return left << half | right


def permuted(value: int, size: int, key: bytes, tweak: bytes, back: bool = False, rounds: int = 8) -> int:
    """Keyed permutation of range(size), or its inverse: a balanced Feistel network, walked until it stays in range."""
    if size < 2:
        return value
    half = max(1, ((size - 1).bit_length() + 1) // 2)
    mask = (1 << half) - 1
    turn = lambda v: (v & mask) << half | v >> half
    while True:
        if back:
            value = turn(_feistel(turn(value), half, key, tweak, range(rounds - 1, -1, -1)))
        else:
            value = _feistel(value, half, key, tweak, range(rounds))
        if value < size:
            return value


def moved(value: int, size: int, key: bytes, tweak: bytes) -> int:
    """Keyed permutation of range(size) that is one cycle: no value stays, if there are two or more."""
    if size < 2:
        return value
    return permuted((permuted(value, size, key, tweak) + 1) % size, size, key, tweak, back=True)


_KINDS: dict[str, tuple[str, str]] = {}


def _script(char: str) -> str:
    return unicodedata.name(char, "?").split(" ")[0].split("-")[0]


def _slot(char: str) -> tuple[str, int] | None:
    """(alphabet, place in it) of a letter or digit, of its small form; None for other characters.

    An alphabet is the letters of one script within a run of 256 code points that behave alike: small letters with one
    capital, or letters without case; vowels apart where the script's are listed. Ideographs and syllables are of one alphabet each.
    """
    if char.isdecimal():
        digit = unicodedata.decimal(char)
        return chr(ord(char) - digit), digit
    low = char.lower()
    if len(low) != 1 or not low.isalpha():
        return None
    if low not in _KINDS:
        code, script = ord(low), _script(low)
        first, last = (0xAC00, 0xD7A4) if script == "HANGUL" and code >= 0xAC00 else (0x4E00, 0xA000) if 0x4E00 <= code < 0xA000 else (code & ~255, (code & ~255) + 256)
        cased = len(low.upper()) == 1 and low.upper() != low and low.upper().lower() == low
        vowel = low in VOWELS.get(script, "")
        plain = script in VOWELS and low in _plain(script)

        def alike(c):
            if not c.isalpha() or c.lower() != c or _script(c) != script:
                return False
            own = len(c.upper()) == 1 and c.upper() != c and c.upper().lower() == c
            return own == cased and (c in VOWELS.get(script, "")) == vowel and (script in VOWELS and c in _plain(script)) == plain

        members = "".join(c for c in map(chr, range(first, last)) if c == low or alike(c))
        for c in members:
            _KINDS[c] = (members, 0)
    members = _KINDS[low][0]
    return members, members.index(low) if len(members) < 600 else ord(low) - ord(members[0])


def _plain(script: str) -> str:
    """Letters without marks of a script with listed vowels."""
    return {"LATIN": "abcdefghijklmnopqrstuvwxyz", "GREEK": "αβγδεζηθικλμνξοπρστυφχψω", "CYRILLIC": "абвгдежзийклмнопрстуфхцчшщъыьэюя"}[script]


def _size(alphabet: str) -> int:
    return 10 if len(alphabet) == 1 and alphabet.isdecimal() else len(alphabet)


def _char(alphabet: str, place: int) -> str:
    return chr(ord(alphabet) + place) if len(alphabet) == 1 and alphabet.isdecimal() else alphabet[place]


def reformatted(text: str, key: bytes, kind: str, fixed: int = 0, accept=None, hexadecimal: bool = False) -> str:
    """Move the letters and digits of ``text`` after the first ``fixed`` characters among strings of its format.

    ``accept`` restricts both the domain and the result; the walk along the cycle goes on until a string is accepted.
    """
    slots = []
    for i, c in enumerate(text):
        own = ("0123456789abcdef", int(c, 16)) if hexadecimal and c in "0123456789abcdefABCDEF" else _slot(c)
        if i >= fixed and own:
            slots.append((i, *own))
    places = {i: a for i, a, _ in slots}
    form = "|".join(f"{places[i][0]}{len(places[i])}" if i in places else c for i, c in enumerate(text))
    tweak, size, value = f"{kind}|{form}|{fixed}".encode("utf-8", "surrogatepass"), 1, 0
    for _, alphabet, place in slots:
        n = _size(alphabet)
        value, size = value * n + place, size * n
    upper = hexadecimal and any(c.isupper() for c in text)
    while True:
        value = moved(value, size, key, tweak)
        out, rest = list(text), value
        for i, alphabet, _ in reversed(slots):
            rest, place = divmod(rest, _size(alphabet))
            c = _char(alphabet, place)
            out[i] = c.upper() if (upper if hexadecimal else text[i].isupper()) else c
        result = "".join(out)
        if accept is None or accept(result):
            return result


def _poured(form: str, digits: str) -> str:
    """The letters and digits of ``form`` replaced by those of ``digits`` in order; other characters stay."""
    rest = iter(digits)
    return "".join(next(rest) if c.isalnum() else c for c in form)


def _luhn_digit(body: str) -> int:
    """Check digit that completes the digits."""
    total = 0
    for k, c in enumerate(reversed(body)):
        d = int(c) * (2 - k % 2)
        total += d - 9 * (d > 9)
    return -total % 10


def _luhn(digits: str) -> bool:
    digits = "".join(c for c in digits if c.isdigit())
    return _luhn_digit(digits[:-1]) == int(digits[-1])


def _iban_check(country: str, body: str) -> int:
    return 98 - int("".join(str(int(c, 36)) for c in f"{body}{country}00")) % 97


# Address ranges by class; all others are public.
_RANGES = {"private": [(10 << 24, 11 << 24), ((172 << 8 | 16) << 16, (172 << 8 | 32) << 16), ((192 << 8 | 168) << 16, (192 << 8 | 169) << 16)], "loop": [(127 << 24, 128 << 24)], "special": [(0, 1 << 24), (224 << 24, 1 << 32)]}


def _gaps(ranges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out, at = [], 0
    for a, b in sorted(ranges):
        out.append((at, a))
        at = b
    return [(a, b) for a, b in [*out, (at, 1 << 32)] if a < b]


_RANGES["public"] = _gaps([r for rs in _RANGES.values() for r in rs])


def _ip(value: str, key: bytes) -> str:
    number = 0
    for part in value.split("."):
        number = number << 8 | int(part)
    name, ranges = next((n, rs) for n, rs in _RANGES.items() if any(a <= number < b for a, b in rs))
    place, size = 0, 0
    for a, b in ranges:
        if a <= number < b:
            place = size + number - a
        size += b - a
    place = moved(place, size, key, f"ip|{name}".encode())
    for a, b in ranges:
        if place < b - a:
            number = a + place
            break
        place -= b - a
    return ".".join(str(number >> s & 255) for s in (24, 16, 8, 0))


def given_name(name: str, key: bytes, gender: str) -> str:
    """Replacement of a given name: within the pool of its gender, or a string of its script with the gender's ending."""
    for g, pool in NAMES.items():
        if name in pool:
            return pool[moved(pool.index(name), len(pool), key, b"given" + g.encode())]
    endings = ENDINGS.get(_script(name[-1].lower()))
    if endings is None:
        return reformatted(name, key, "given")
    ending = endings[gender]
    return reformatted(name, key, f"given{gender}") + (ending.upper() if name.isupper() and len(name) > 1 else ending)


def identity(kind: str, value: str) -> str:
    """What all spellings of one entity have in common."""
    if kind in ("iban", "card", "phone", "ssn"):
        return ("+" if value.startswith("+") else "") + "".join(c for c in value if c.isalnum())
    return value.lower() if kind == "email" else value


def surrogate(kind: str, value: str, key: bytes, gender: str = "n") -> str:
    """Replacement of one entity in the format of its value; equal identities give equal identities under one key."""
    plain = identity(kind, value)
    if kind == "email":
        local, _, domain = value.rpartition("@")
        name, dot, rest = domain.partition(".")
        return f"{reformatted(local, key, 'local')}@{reformatted(name, key, 'domain')}{dot}{rest}"
    if kind == "card":
        digits = plain
        body = reformatted(digits[:-1], key, f"card{len(digits)}", 1)
        off = int(digits[-1]) - _luhn_digit(digits[:-1])  # 0: valid
        return _poured(value, body + str((_luhn_digit(body) + off) % 10))
    if kind == "phone":
        digits = plain.lstrip("+")
        code = next((n for n in (1, 2) if digits[:n] in CALLING), 3) if plain[0] == "+" else int(digits[0] == "0")
        return _poured(value, reformatted(digits, key, f"phone{plain[0] == '+'}", min(code, len(digits) - 1)))
    if kind == "ssn":
        real = lambda s: s[:3] not in ("000", "666") and s[0] != "9" and s[3:5] != "00" and s[5:] != "0000"
        valid = real(plain)
        return _poured(value, reformatted(plain, key, f"ssn{valid}", accept=lambda s: real(s) == valid))
    if kind == "ip":
        return _ip(value, key)
    if kind == "iban":
        country, check, body = plain[:2], int(plain[2:4]), plain[4:]
        new = reformatted(body, key, f"iban{country}")
        off = check - _iban_check(country, body)  # 0: valid
        return _poured(value, f"{country}{(_iban_check(country, new) + off) % 100:02d}{new}")
    if kind == "credential":
        whole = re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", value) is not None
        return reformatted(value, key, kind + ("hex" + "uU"[value.isupper()] if whole else ""), hexadecimal=whole)
    if kind == "given":
        return given_name(value, key, gender)
    return reformatted(value, key, kind)


def _name_words(found: str) -> list[str]:
    """The words after a title that can be a name: the first, and those after it that do not begin small."""
    words = found.split(" ")
    if words[0][0].islower() or len(words[0]) < 2:
        return []
    caseless = words[0].lower() == words[0].upper()
    out = [words[0]]
    for w in words[1 : 2 if caseless else 3]:
        if w[0].islower() or len(w) < 2 or (w.lower() == w.upper()) != caseless:
            break
        out.append(w)
    return out


def entities(text: str):
    """(kind, start, end, value, gender) of each entity, in order; a person's words are entities of kind given or family."""
    if not _WORTH.search(text):
        return
    found, roles = [], {}  # word -> (role, gender): the document's own persons
    for m in ENTITY.finditer(text):
        if m.lastgroup not in ("person", "title"):
            found.append((m.lastgroup, m.start(m.lastgroup), m.end(m.lastgroup), m.group(m.lastgroup), "n"))
            continue
        gender, at = _GENDER[m.group("title")], m.start("person")
        words = _name_words(m.group("person"))
        for k, w in enumerate(words):
            known = next((g for g, pool in NAMES.items() if w in pool), None)
            role = "given" if k < len(words) - 1 else "family"
            if w not in roles or (role == "given" and roles[w][0] == "family" and known):
                roles[w] = (role, known or gender if role == "given" else "n")
            elif role == "given" and roles[w] == ("given", "n"):
                roles[w] = (role, known or gender)
            found.append(("name", at, at + len(w), w, "n"))
            at += len(w) + 1
    if roles:
        taken = [(a, b) for _, a, b, _, _ in found]
        word = re.compile(r"(?<!\w)(?:" + "|".join(sorted(map(re.escape, roles), key=len, reverse=True)) + r")(?!\w)")
        found += [("name", m.start(), m.end(), m.group(), "n") for m in word.finditer(text) if not any(a < m.end() and m.start() < b for a, b in taken)]
        found.sort(key=lambda e: e[1])
    for kind, a, b, value, gender in found:
        if kind == "name":
            kind, gender = roles[value]
        yield kind, a, b, value, gender


def replaced(text: str, key: bytes, memo: dict) -> tuple[str, list[tuple[str, str, str, int, int]]]:
    """The text with surrogates, and (kind, value, surrogate, start, end) of each entity."""
    parts, found, at = [], [], 0
    for kind, a, b, value, gender in entities(text):
        name = (kind, value, gender)
        if name not in memo:
            if len(memo) > 50_000:
                memo.clear()
            memo[name] = surrogate(kind, value, key, gender)
        parts += [text[at:a], memo[name]]
        found.append((kind, value, memo[name], a, b))
        at = b
    return ("".join([*parts, text[at:]]) if found else text), found


def _digest(kind: str, value: str, of: dict) -> int:
    if (kind, value) not in of:
        import xxhash

        if len(of) > 100_000:
            of.clear()
        group = "name" if kind in ("given", "family") else kind
        of[kind, value] = xxhash.xxh3_64_intdigest(f"{kind}|{identity(group, value)}".encode()) - (1 << 63)
    return of[kind, value]


class Collision(ValueError):
    """Two entities got one surrogate, or one entity two."""


def pseudonymised(docs: DataFrame, key: bytes, text: str = "text", count: str | None = None, check: bool = True) -> DataFrame:
    """The same rows and columns with surrogates in the text column; ``count`` names a column for the entities found.

    With ``check`` the result is written once and its collisions are counted over the corpus, by digests of entities and
    surrogates that were noted with each row; ``Collision`` is raised if there are any.
    """
    if count is not None and count in docs.columns:
        raise ValueError(f"the documents have a column {count}")
    place = docs.columns.index(text)
    noted = "noted"
    while noted in (*docs.columns, count):
        noted += "_"
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)

    def change(batches):
        memo, of = {}, {}
        pair = pa.list_(pa.struct([("v", pa.int64()), ("s", pa.int64())]))
        for batch in batches:
            texts, counts, notes = [], [], []
            for value in batch.column(place).to_pylist():
                new, found = (value, ()) if value is None else replaced(value, key, memo)
                texts.append(new)
                counts.append(len(found))
                notes.append([{"v": v, "s": s} for v, s in {(_digest(k, v, of), _digest(k, s, of)) for k, v, s, _, _ in found}])
            columns = list(batch.columns)
            columns[place] = pa.array(texts, pa.string())
            if count:
                columns.append(pa.array(counts, pa.int64()))
            columns.append(pa.array(notes, pair))
            yield pa.RecordBatch.from_arrays(columns, [*batch.schema.names, *([count] if count else []), noted])

    out = docs.mapInArrow(change, schema + (f", `{count}` long" if count else "") + f", `{noted}` array<struct<v:long,s:long>>")
    if not check:
        return out.drop(noted)
    out = written(out, "surrogates")
    bad = _colliding(out.select(F.explode(noted).alias("n")).select("n.v", "n.s")).limit(1).count()
    if bad:
        raise Collision("surrogates collide; see collisions()")
    return out.drop(noted)


def _colliding(pairs: DataFrame) -> DataFrame:
    """Rows for surrogates of several entities and entities of several surrogates; sums combine before the exchange."""
    one = lambda a, b: pairs.groupBy(a).agg(F.min(b).alias("lo"), F.max(b).alias("hi")).where("lo <> hi").select(F.lit(a).alias("side"), F.col(a).alias("digest"))
    return one("s", "v").unionByName(one("v", "s"))


def entity_table(docs: DataFrame, key: bytes) -> DataFrame:
    """(doc_id, kind, value, surrogate, start, end) of every entity; offsets are code points of the original text."""

    def find(batches):
        memo: dict = {}
        for batch in batches:
            rows = [(d, *f) for d, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) if t for f in replaced(t, key, memo)[1]]
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 6
            kinds = (pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["doc_id", "kind", "value", "surrogate", "start", "end"])

    return docs.select("doc_id", "text").mapInArrow(find, "doc_id long, kind string, value string, surrogate string, start long, end long")


def collisions(docs: DataFrame, key: bytes) -> DataFrame:
    """(kind, surrogate, n_values): surrogates of several entities, upper and lower case apart; empty if all is well."""
    return entity_table(docs, key).groupBy("kind", "surrogate").agg(F.countDistinct("value").alias("n_values")).where("n_values > 1")
