"""Personal data replaced by keyed surrogates of the same type and format.

Every entity is mapped by a keyed permutation of the set of all entities of its type and format (a Feistel network with
cycle walking, conjugating a shift so that nothing maps to itself). A permutation is one-to-one, so different entities
keep different surrogates and one entity has one surrogate in all documents, tasks and retries, without a table or a
shuffle. What a surrogate must keep is part of the set: check digits stay valid or invalid, addresses stay private
or public, letters keep case and script, vowels stay vowels, dates stay dates. A name is mapped word by word, whatever
title, place or number of words it comes with, so Julia Weber, Dr Weber and a later Weber without a title agree; words of
the lists stay in their list and so keep their gender, all others follow one map that leaves the lists out.

A name is found after a title, or as a listed given name before a capitalised word; its words are then found throughout
the text. Other names, postal addresses and the like are not found. Every row tells whether its entities and surrogates
are one to one; `collisions` is that check over a whole table.

Null texts stay null, texts without entities stay as they are. Invalid look-alikes (an address with a part over 255, an
account number with a wrong check) are not entities of that type. Texts of any length are read whole; repeated rows are
treated alike; other columns may have any name. An empty table gives no rows.
"""

from __future__ import annotations

import datetime
import hashlib
import ipaddress
import re
import unicodedata
from bisect import bisect_left
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from saferoads.llm.blocks import lean

#: Given names and family names for surrogates of listed names.
FEMALE = "anna emma julia laura marie sofia claire elena hanna lucia nadia petra rosa sara vera".split()
MALE = "adam bruno carlos david emil felix hugo ivan jonas karl leo martin oscar paul simon".split()
FAMILY = "adler bauer costa dupont evans fischer garcia hansen keller lambert moreno novak olsen petit rossi silva torres vidal weber young".split()
#: Titles that tell a gender.
TITLES = {"mr": "m", "herr": "m", "señor": "m", "sr": "m", "monsieur": "m", "mrs": "f", "ms": "f", "miss": "f", "frau": "f", "señora": "f", "sra": "f", "madame": "f", "mme": "f", "dr": "n", "prof": "n"}

CLASSES = ["0123456789", "aeiou", "bcdfghjklmnpqrstvwxyz", "áéíóúàèìòùâêîôûäëïöü", "çñß", "аеиоуыэюя", "бвгджзйклмнпрстфхцчшщьъ", "αεηιουω", "βγδζθκλμνξπρσςτφχψ"]
CLASS_OF = {c: cls for cls in CLASSES for c in cls}

PATTERN = re.compile(
    r"""
    (?P<email>[\w.%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+)
  | (?P<secret>(?i:\b(?:token|secret|password|passwd|api[_-]?key|access[_-]?key)\b["']?\s*[=:]\s*)["']?(?P<value>[A-Za-z0-9_+/.-]{8,}=*))
  | (?P<hex>\b(?:[0-9a-f]{32,}|[0-9A-F]{32,})\b)
  | (?P<iban>\b[A-Z]{2}\d{2}(?:[ ]?[A-Z0-9]{4}){2,7}(?:[ ]?[A-Z0-9]{1,3})?\b)
  | (?P<birth>(?i:\b(?:born(?:[ ]on)?|date[ ]of[ ]birth|dob|geboren[ ]am|née?[ ]le|nacid[oa][ ]el)\b[: ]*)(?P<day>\d{4}-\d{2}-\d{2}|\d{2}[./]\d{2}[./]\d{4})\b)
  | (?P<ip6>(?<![\w:.])(?=[0-9A-Fa-f]{0,4}:)(?:[0-9A-Fa-f]{0,4}:){2,7}[0-9A-Fa-f]{0,4}(?![\w:]))
  | (?P<ip>(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?![\d]|\.\d))
  | (?P<phone>\+\d{1,3}[ .-]?(?:\(\d{1,4}\)[ .-]?)?\d{2,4}(?:[ .-]?\d{2,4}){1,4}\b|\(\d{3}\)[ ]?\d{3}[ .-]\d{4}\b|(?<![\d.-])\d{3}[.-]\d{3}[.-]\d{4}(?![\d.-]))
  | (?P<ssn>(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-]))
  | (?P<card>(?<![\d.])\d(?:[ -]?\d){12,18}(?![\d]))
  | (?P<name>\b(?P<title>(?i:Mr|Mrs|Ms|Miss|Dr|Prof|Herr|Frau|Señora?|Sra?|Monsieur|Madame|Mme))\b\.?[ ](?P<person>[^\W\d_a-z][\w'’-]+(?:[ ][^\W\d_a-z][\w'’-]+)?))
    """,
    re.X,
)
GIVEN = "|".join(x.capitalize() for x in sorted(FEMALE + MALE))
#: A listed given name before a capitalised word.
UNTITLED = re.compile(rf"\b(?:{GIVEN})[ ][^\W\d_a-z][\w'’-]+")
#: A text without any of these has no entity.
HINT = re.compile(rf"[0-9@]|::|(?i:token|secret|passw|key|mr|ms\b|miss|dr\b|prof|herr|frau|señor|sra?\b|monsieur|madame|mme)|\b(?:{GIVEN})[ ]")


class Permutation:
    """Keyed one-to-one map of 0..size-1 without a fixed point (size 2 at least)."""

    def __init__(self, key: bytes, label: str, size: int):
        self.key, self.label, self.size = key, label.encode()[:200], size
        self.bits = max((size - 1).bit_length() + 1, 2) // 2
        self.mask = (1 << self.bits) - 1
        self.shift = 1 + int.from_bytes(self._digest(b"shift", 0), "big") % (size - 1)

    def _digest(self, purpose: bytes, value: int) -> bytes:
        return hashlib.blake2b(self.label + b"|" + purpose + b"|" + value.to_bytes(32 + self.bits // 8, "big"), key=self.key, digest_size=min(8 + self.bits // 8, 64)).digest()

    def _rounds(self, x: int, order) -> int:
        left, right = x >> self.bits, x & self.mask
        if order == 1:
            for r in range(6):
                left, right = right, left ^ int.from_bytes(self._digest(b"%d" % r, right), "big") & self.mask
        else:
            for r in range(5, -1, -1):
                left, right = right ^ int.from_bytes(self._digest(b"%d" % r, left), "big") & self.mask, left
        return left << self.bits | right

    def _walk(self, x: int, order: int) -> int:
        x = self._rounds(x, order)
        while x >= self.size:
            x = self._rounds(x, order)
        return x

    def __call__(self, x: int) -> int:
        return self._walk((self._walk(x, 1) + self.shift) % self.size, -1)


def shuffled(key: bytes, label: str, text: str, alphabets: list[str], allowed=lambda s: True) -> str:
    """Image of text among all strings over the alphabets (one for each position) that are allowed, as text is."""
    size = 1
    for a in alphabets:
        size *= len(a)
    if size < 2:
        return text
    turn = Permutation(key, f"{label}|{[a[:2] + str(len(a)) for a in alphabets]}", size)
    rank = 0
    for c, a in zip(text, alphabets, strict=True):
        rank = rank * len(a) + a.index(c)
    while True:
        rank = x = turn(rank)
        out = []
        for a in reversed(alphabets):
            x, c = divmod(x, len(a))
            out.append(a[c])
        found = "".join(reversed(out))
        if allowed(found):
            return found


@lru_cache(maxsize=4096)
def alphabet_of(c: str) -> str:
    """The class of a letter or digit; letters of other scripts go with those of their kind among 256 neighbours. Empty for
    all else."""
    if c in CLASS_OF:
        return CLASS_OF[c]
    if not c.isalpha():
        return ""
    first, kind = ord(c) & ~255, unicodedata.category(c)
    near = (chr(x) for x in range(first, first + 256))
    return "".join(x for x in near if unicodedata.category(x) == kind and x not in CLASS_OF and x.lower() == x)


def by_class(key: bytes, label: str, text: str, allowed=lambda s: True) -> str:
    """Letters for letters of their class, digits for digits, case by case; all other characters stay."""
    low = text.lower()
    if len(low) != len(text):
        low = text
    at = [i for i, c in enumerate(low) if c in alphabet_of(c)]

    def whole(s: str) -> str:
        chars = list(low)
        for i, c in zip(at, s, strict=True):
            chars[i] = c
        return "".join(chars)

    moved = set(at)
    frame = "".join("·" if i in moved else c for i, c in enumerate(low))
    image = whole(shuffled(key, f"{label}|{frame}", "".join(low[i] for i in at), [alphabet_of(low[i]) for i in at], lambda s: allowed(whole(s))))
    return "".join(c.upper() if o.isupper() else c for c, o in zip(image, text, strict=True))


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        x = int(c) * (1 + i % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def refill(frame: str, digits: str) -> str:
    it = iter(digits)
    return "".join(next(it) if c.isdigit() else c for c in frame)


def iban_check(country: str, rest: str) -> str:
    number = int("".join(str(int(c, 36)) for c in rest + country + "00"))
    return f"{98 - number % 97:02d}"


def network(ip: str) -> int:
    a, b, *_ = map(int, ip.split("."))
    return 1 if a == 10 else 2 if a == 172 and 16 <= b < 32 else 3 if (a, b) == (192, 168) else 4 if a == 127 else 5 if a == 0 or a >= 224 else 0


def surrogate(key: bytes, kind: str, text: str, gender: str = "n") -> str | None:
    """The surrogate of one entity; None if the text is not one of that kind after all. The gender that a title tells changes
    nothing: a listed name keeps its own."""
    if kind == "email":
        local, _, domain = text.lower().rpartition("@")
        host, _, tld = domain.rpartition(".")
        image = f"{by_class(key, 'local', local)}@{by_class(key, 'domain', host)}.{tld}"
        return "".join(c.upper() if o.isupper() else c for c, o in zip(image, text, strict=True)) if len(image) == len(text) else image
    if kind == "ip":
        parts = text.split(".")
        if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
            return None
        rank = 0
        for p in parts:
            rank = rank << 8 | int(p)
        turn, home = Permutation(key, "ip", 1 << 32), network(text)
        while True:
            rank = turn(rank)
            found = ".".join(str(rank >> s & 255) for s in (24, 16, 8, 0))
            if network(found) == home:
                return found
    if kind in ("secret", "hex"):
        for alphabet in ("0123456789abcdef", "0123456789ABCDEF"):
            if len(text) >= 16 and set(text) <= set(alphabet):
                return shuffled(key, "hex", text, [alphabet] * len(text))
        return by_class(key, "secret", text)
    digits = "".join(c for c in text if c.isdigit())
    if kind == "card":
        body = digits[1:]
        valid = luhn(digits)
        image = shuffled(key, f"card|{digits[0]}|{valid}", body, ["0123456789"] * len(body), lambda s: luhn(digits[0] + s) == valid)
        return refill(text, digits[0] + image)
    if kind == "phone":
        code = len(re.match(r"\+(\d{1,3})(?=[ .(-])|", text)[0][1:]) if text[0] == "+" else 0
        body = digits[code:]
        first = "123456789" if body[0] != "0" else "0"
        image = shuffled(key, f"phone|{re.sub(chr(92) + 'd', '0', text)}|{digits[:code]}", body, [first] + ["0123456789"] * (len(body) - 1))
        return refill(text, digits[:code] + image)
    if kind == "ssn":
        return refill(text, shuffled(key, "ssn", digits, ["0123456789"] * 9, lambda s: s[:3] != "000"))
    if kind == "iban":
        plain = text.replace(" ", "")
        if iban_check(plain[:2], plain[4:]) != plain[2:4]:
            return None
        rest = shuffled(key, f"iban|{plain[:2]}|{len(plain)}", plain[4:], ["0123456789" if c.isdigit() else "ABCDEFGHIJKLMNOPQRSTUVWXYZ" for c in plain[4:]])
        whole = iter(plain[:2] + iban_check(plain[:2], rest) + rest)
        return "".join(c if c == " " else next(whole) for c in text)
    if kind == "birth":
        parts = [int(x) for x in re.findall(r"\d+", text)]
        year, month, day = parts if len(str(parts[0])) == 4 else parts[::-1]
        try:
            rank = datetime.date(year, month, day).toordinal() - FIRST_DAY
        except ValueError:
            return None
        if not 0 <= rank < DAYS:
            return None
        found = datetime.date.fromordinal(FIRST_DAY + Permutation(key, "birth", DAYS)(rank))
        mark = text[2] if text[2] in "./" else "-"
        return found.isoformat() if mark == "-" else found.strftime(f"%d{mark}%m{mark}%Y")
    if kind == "ip6":
        try:
            ipaddress.IPv6Address(text)
        except ValueError:
            return None
        kept = text.index(":")  # the first group tells the kind of network
        hexes = "0123456789ABCDEF" if any(c.isupper() for c in text) else "0123456789abcdef"
        at = [i for i, c in enumerate(text.lower() if hexes.islower() else text) if i > kept and c in hexes]
        if not at:
            return None
        image = list(text)
        leading = {i for i in at if text[i - 1] == ":" and text[i] != "0"}
        frame = "".join("·" if i in set(at) else c for i, c in enumerate(text))
        for i, c in zip(at, shuffled(key, f"ip6|{frame}", "".join(text[i] for i in at), [hexes[1:] if i in leading else "0" if text[i - 1] == ":" else hexes for i in at]), strict=True):
            image[i] = c
        return "".join(image)
    if kind == "name":
        return " ".join(name_word(key, word) for word in text.split(" "))
    raise ValueError(kind)


FIRST_DAY = datetime.date(1900, 1, 1).toordinal()
DAYS = datetime.date(2100, 1, 1).toordinal() - FIRST_DAY
LISTED = {name: names for names in (MALE, FEMALE, FAMILY) for name in names}


def name_word(key: bytes, word: str) -> str:
    """One map for all words of names: a listed one stays in its list, the others stay outside the lists."""
    low = word.lower()
    if low not in LISTED:
        return by_class(key, "name", word, lambda s: s not in LISTED)
    names = LISTED[low]
    image = names[Permutation(key, f"name|{names[0]}", len(names))(names.index(low))]
    return image.upper() if word.isupper() else image.capitalize()


def entities_of(text: str):
    """(start, end, kind, gender) of entities, left to right, without overlaps: first all by pattern, then the words of the
    names among them wherever they stand alone."""
    found = list(by_pattern(text))
    taken = [(a, b) for a, b, _, _ in found]
    for m in UNTITLED.finditer(text):
        if free(taken, m.start(), m.end()):
            found.append((m.start(), m.end() - owner(m[0]), "name", "n"))
    known = {w for a, b, kind, _ in found if kind == "name" for w in text[a:b].split(" ") if len(w) > 2}
    if known:
        taken = sorted((a, b) for a, b, _, _ in found)
        for m in re.finditer(rf"(?<!\w)(?:{'|'.join(sorted(map(re.escape, known)))})(?!\w)", text):
            if free(taken, m.start(), m.end()):
                found.append((m.start(), m.end(), "name", "n"))
    return sorted(found)


def free(taken: list[tuple[int, int]], start: int, end: int) -> bool:
    """Whether start..end meets none of the sorted stretches."""
    at = bisect_left(taken, (end,))
    return at == 0 or taken[at - 1][1] <= start


def owner(name: str) -> int:
    """Length of an ending that marks an owner and is no part of the name."""
    return 2 if name.endswith(("'s", "’s")) else 0


def by_pattern(text: str):
    for m in PATTERN.finditer(text):
        kind = m.lastgroup
        if m["secret"] is not None:
            yield m.start("value"), m.end("value"), "secret", "n"
        elif m["birth"] is not None:
            yield m.start("day"), m.end("day"), "birth", "n"
        elif m["name"] is not None:
            yield m.start("person"), m.end("person") - owner(m["person"]), "name", TITLES[m["title"].lower()]
        else:
            yield m.start(), m.end(), kind, "n"


def replaced(text: str, key: bytes, memory: dict) -> tuple[str, list[tuple[str, str, str]]]:
    """Text with surrogates, and (kind, entity, surrogate) of each place. memory: recent surrogates, bounded."""
    if not HINT.search(text):
        return text, []
    out, last, found = [], 0, []
    for a, b, kind, gender in entities_of(text):
        entity = (kind, text[a:b], gender)
        if entity not in memory:
            if len(memory) >= 100_000:
                memory.clear()
            memory[entity] = surrogate(key, *entity)
        image = memory[entity]
        if image is None:
            continue
        out += [text[last:a], image]
        last = b
        found.append((kind, text[a:b], image))
    return "".join(out) + text[last:], found


def one_to_one(found: list[tuple[str, str, str]]) -> bool:
    pairs = set(found)
    return len({(k, e) for k, e, _ in pairs}) == len(pairs) == len({(k, x) for k, _, x in pairs})


def replace_entities(docs: DataFrame, key: str, keep_columns: bool = False) -> DataFrame:
    """Per row doc_id, n_entities, kinds (sorted), text with surrogates, and whether the row's entities and surrogates are one
    to one; or with keep_columns the columns of docs."""
    secret, names = key.encode(), docs.columns
    schema = docs.schema if keep_columns else "doc_id bigint, n_entities int, kinds array<string>, text string, one_to_one boolean"

    @lean
    def run(batches):
        memory: dict = {}
        for batch in batches:
            texts = batch.column("text")
            done = [(None, []) if t is None else replaced(t, secret, memory) for t in texts.to_pylist()]
            fresh = [t for t, _ in done]
            if keep_columns:
                columns = [pa.array(fresh, texts.type) if c == "text" else batch.column(c) for c in names]
                if "n_chars" in names:
                    i = names.index("n_chars")
                    columns[i] = pa.array([len(t) if f else n for (t, f), n in zip(done, batch.column("n_chars").to_pylist(), strict=True)], columns[i].type)
                yield pa.RecordBatch.from_arrays(columns, names)
            else:
                kinds = [sorted({k for k, _, _ in f}) for _, f in done]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), pa.array([len(f) for _, f in done], pa.int32()), pa.array(kinds, pa.list_(pa.string())), pa.array(fresh, pa.string()), pa.array([one_to_one(f) for _, f in done])], ["doc_id", "n_entities", "kinds", "text", "one_to_one"])

    return (docs if keep_columns else docs.select("doc_id", "text")).mapInArrow(run, schema)


def entity_table(docs: DataFrame, key: str) -> DataFrame:
    """kind, entity, surrogate of every place in every text."""
    secret = key.encode()

    @lean
    def run(batches):
        memory: dict = {}
        for batch in batches:
            found = [x for t in batch.column("text").to_pylist() if t is not None for x in replaced(t, secret, memory)[1]]
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in zip(*found, strict=True)], ["kind", "entity", "surrogate"])

    return docs.select("text").mapInArrow(run, "kind string, entity string, surrogate string")


def collisions(docs: DataFrame, key: str) -> DataFrame:
    """Surrogates that stand for several entities, and entities with several surrogates: none are expected."""
    table = entity_table(docs, key).distinct()
    by_surrogate = table.groupBy("kind", "surrogate").agg(F.count_distinct("entity").alias("n")).select("kind", F.col("surrogate").alias("value"), "n")
    by_entity = table.groupBy("kind", "entity").agg(F.count_distinct("surrogate").alias("n")).select("kind", F.col("entity").alias("value"), "n")
    return by_surrogate.unionAll(by_entity).where("n > 1")
