"""Operator 1, personal data: keyed surrogates of the same type, gender, script and format.

Finders locate e-mail addresses, telephone numbers, payment cards (valid check digit), social security numbers, account numbers (IBAN), network
addresses (both versions), secrets (a named token, or a long run of hexadecimal digits) and person names (after a title, with initials, or a known given name
followed by a capitalised one; before a Chinese or Japanese title; later bare mentions of a found surname in the same text are names too).

A surrogate is a keyed bijection of the entity's own domain: letters go to letters of the same script, case and, for names, vowel or
consonant; digits to digits; separators stay.  The value's rank in its domain is moved one step along a keyed cycle through the
whole domain (a Feistel permutation, a step, and its inverse), so no entity keeps its value, two entities of one format never get the
same surrogate, and the same entity gets the same one in every document, without any table.  Given names move within the list of their
script and gender; other forenames keep their last letter, and surnames the ending that carries gender.  Where a kind has classes (endings, hexadecimal
secrets), a value walks on along its cycle until it is in its own class again, so the images of classes don't meet.  Two formats of one number are two
entities.  ``collisions`` checks distinctness over a corpus all the same, and ``checked`` counts them for each document; nothing in a text raises.

Edge cases: null texts stay null and count 0; empty texts stay empty; repeated rows and entities get equal surrogates; null ids pass
through; other columns are not read.
"""

from __future__ import annotations

import hashlib
import ipaddress
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Given names by script and gender; each list is one domain.
GIVEN = {
    ("latin", "f"): "Alice Anna Barbara Carmen Charlotte Claire Clara Elena Elizabeth Emily Emma Eva Hannah Helen Ingrid Isabel Jane Julia Laura Linda Lucia Maria Marie Martha Mary Nina Olivia Patricia Rosa Sarah Sofia Sophie Susan Teresa Ursula María Sofía Lucía Inés Chloé Amélie Hélène Zoë Agnieszka Katarzyna Małgorzata Ayşe Žaneta".split(),
    ("latin", "m"): "Adam Alexander Andrew Anton Antonio Benjamin Carlos Charles Daniel David Edward Felix Francisco Frank George Hans Henry Jack James Jean John Jose Karl Louis Luis Marc Martin Michael Miguel Oliver Paul Peter Pierre Robert Thomas William José Jesús Andrés Ángel Raúl Óscar François André René Jérôme Jürgen Jörg Łukasz Paweł Michał Tomasz Slavoj".split(),
    ("cyrillic", "f"): "Анна Вера Екатерина Елена Ирина Мария Наталья Ольга Светлана Татьяна".split(),
    ("cyrillic", "m"): "Александр Алексей Андрей Борис Виктор Дмитрий Иван Михаил Николай Сергей".split(),
}
TITLES = ["Mr", "Mrs", "Ms", "Miss", "Dr", "Prof", "Herr", "Frau", "Monsieur", "Madame", "Mme", "Señor", "Señora", "Sr", "Sra", "Господин", "Госпожа", "Κύριος", "Κυρία"]
#: Endings that carry gender and stay.
ENDINGS = ("ова", "ева", "ина", "ая", "ов", "ев", "ин", "ий")
ALPHABETS = [
    "0123456789",
    "bcdfghjklmnpqrstvwxz", "aeiouy", "BCDFGHJKLMNPQRSTVWXZ", "AEIOUY",
    "бвгджзйклмнпрстфхцчшщ", "аеёиоуыэюя", "БВГДЖЗЙКЛМНПРСТФХЦЧШЩ", "АЕЁИОУЫЭЮЯ",
    "βγδζθκλμνξπρστφχψ", "αεηιουω", "ΒΓΔΖΘΚΛΜΝΞΠΡΣΤΦΧΨ", "ΑΕΗΙΟΥΩ",
    "çñß", "àáâäãåèéêëìíîïòóôöõøùúûüýÿ", "ÇÑ", "ÀÁÂÄÃÅÈÉÊËÌÍÎÏÒÓÔÖÕØÙÚÛÜÝ",
]
#: Blocks whose remaining letters are one alphabet for each case: Latin, Greek and Cyrillic beyond the ones above, Hebrew, Arabic, Devanagari, Thai,
#: Hiragana, Katakana, Han, Hangul.
BLOCKS = [(0xC0, 0x24F), (0x370, 0x3FF), (0x400, 0x52F), (0x5D0, 0x5EA), (0x621, 0x64A), (0x904, 0x939), (0xE01, 0xE2E), (0x3041, 0x3096), (0x30A1, 0x30FA), (0x4E00, 0x9FFF), (0xAC00, 0xD7A3)]


def _rest_of(block: tuple[int, int]) -> list[str]:
    """The letters of a block that no listed alphabet has, lower and other cases apart from upper."""
    known = set("".join(ALPHABETS))
    free = [c for c in map(chr, range(block[0], block[1] + 1)) if c.isalpha() and c not in known]
    return ["".join(c for c in free if c.isupper() == upper) for upper in (False, True)]


ALPHABETS += [a for block in BLOCKS for a in _rest_of(block) if len(a) > 1]
_NUMBER = {a: i for i, a in enumerate(ALPHABETS)}
CLASS = {c: (a, i) for a in ALPHABETS for i, c in enumerate(a)}
HEX = "0123456789abcdef"
#: Frequent Chinese surnames, which a title follows.
HAN_SURNAMES = "王李张刘陈杨黄赵吴周徐孙马朱胡郭何高林郑"

_given = {n: (names, i) for names in GIVEN.values() for i, n in enumerate(names)}
_upper = "[A-Z" + "".join(c for lo, hi in BLOCKS[:3] for c in map(chr, range(lo, hi + 1)) if c.isupper()) + "]"
_name = _upper + r"[\w'’-]*[^\W\d_]"
EMAIL = re.compile(r"[\w.%+-]+@(?:[^\W_](?:[\w-]*[^\W_])?\.)+[^\W\d_]{2,}")
SECRET = re.compile(r"(?i:\b(?:token|secret|password|passwd|api[_-]?key|access[_-]?key)\b\s*[:=]\s*)([\"'])([^\"'\s]{6,})\1|\b([0-9a-f]{32,})\b")
NUMBER = re.compile(r"(?<!\w)(?<!\d\.)(?:\d{1,3}(?:\.\d{1,3}){3}(?![\w]|\.\d)|\d{3}-\d{2}-\d{4}(?![\w-])|\d(?:[ -]?\d){12,18}(?![\w-])|\+\d{1,3}[ .-]?(?:\(\d{1,4}\)[ .-]?)?\d{2,4}(?:[ .-]?\d{2,4}){1,4}(?!\w)|\(\d{3}\) ?\d{3}-\d{4}(?!\w)|\d{3}[.-]\d{3}[.-]\d{4}(?!\w)|0\d{2,4}[ -]\d{3,4}[ -]?\d{3,4}(?![\w-]))")
IBAN = re.compile(r"\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b")
V6 = re.compile(r"(?<![\w:.])(?=[0-9A-Fa-f:]*:[0-9A-Fa-f:]*:)[0-9A-Fa-f:]{2,39}(?![\w:])")
_initials = rf"(?:({_upper})\.? ?)?(?:({_upper})\. ?)?"
NAME = re.compile(rf"\b(?:(?:{'|'.join(TITLES)})\.? {_initials}({_name})(?: ({_name}))?|({'|'.join(sorted(_given, key=len, reverse=True))}) (?:({_upper})\. ?)?({_name})(?: ({_name}))?)")
#: Groups of NAME by their place in a name.
_INITIAL, _FIRST, _LAST = {1, 2, 6}, {3}, {4, 5, 7, 8}
EAST = re.compile(rf"([{HAN_SURNAMES}])(?=先生|女士|小姐)|(?<![\u4e00-\u9fff])([\u4e00-\u9fff]{{2,3}})(?=さん|様)")
_digit = re.compile(r"\d{2}|\(\d{3}\)").search
_hint = re.compile(r"\b(?:" + "|".join([*TITLES, *_given]) + r")\b").search


def luhn(digits: str) -> int:
    """The check sum of a card number, 0 where it is valid."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 if d > 9 else d
    return total % 10


def iban_ok(value: str) -> bool:
    v = value.replace(" ", "")
    return 15 <= len(v) <= 34 and int("".join(str(int(c, 36)) for c in v[4:] + v[:4])) % 97 == 1


class Keyed:
    """Keyed permutations of ranges of integers and of strings of one format."""

    def __init__(self, key: bytes, rounds: int = 8):
        self.key, self.rounds = key[:64], rounds

    def _round(self, i: int, x: int, tweak: str, bits: int) -> int:
        h = hashlib.blake2b(f"{i}|{x}|{tweak}".encode(), key=self.key, digest_size=min(64, max(8, bits // 8 + 1))).digest()
        return int.from_bytes(h, "big") & ((1 << bits) - 1)

    def _walk(self, x: int, n: int, tweak: str, back: bool) -> int:
        half = max(1, (n - 1).bit_length() + 1 >> 1)
        low = (1 << half) - 1
        while True:  # until the value is in the range again
            a, b = x >> half, x & low
            if back:
                for i in reversed(range(self.rounds)):
                    a, b = b ^ self._round(i, a, tweak, half), a
            else:
                for i in range(self.rounds):
                    a, b = b, a ^ self._round(i, b, tweak, half)
            x = a << half | b
            if x < n:
                return x

    def step(self, x: int, n: int, tweak: str) -> int:
        """The successor of x on a keyed cycle through all of range(n): a bijection without fixed points for n > 1."""
        if n < 2:
            return x
        return self._walk((self._walk(x, n, tweak, False) + 1) % n, n, tweak, True)

    def text(self, value: str, tweak: str, classes: dict[str, tuple[str, int]] = CLASS) -> str:
        """Move a string within its format; letters of no known alphabet stay."""
        kinds = [classes.get(c) for c in value]
        x, n = 0, 1
        for k in kinds:
            if k:
                x, n = x * len(k[0]) + k[1], n * len(k[0])
        # the format itself is part of the key, so each format has a cycle of its own
        shape = "".join(c if k is None else chr(0xE000 + _NUMBER.get(k[0], 0x100)) for c, k in zip(value, kinds, strict=True))
        y = self.step(x, n, f"{tweak}|{shape}")
        out = []
        for c, k in zip(reversed(value), reversed(kinds), strict=True):
            if k:
                y, r = divmod(y, len(k[0]))
                c = k[0][r]
            out.append(c)
        return "".join(reversed(out))


_hex = {c: (HEX, i) for i, c in enumerate(HEX)}
_is_hex = re.compile(r"[0-9a-f]{16,}").fullmatch


def _ending(name: str) -> str:
    return next((e for e in ENDINGS if name.endswith(e) and len(name) > len(e) + 1), "")


class Surrogates:
    def __init__(self, key: bytes):
        self.k = Keyed(key)
        self.memo: dict[tuple[str, str], str] = {}

    def of(self, kind: str, value: str) -> str:
        if (got := self.memo.get((kind, value))) is None:
            if len(self.memo) > 100_000:
                self.memo.clear()
            got = self.memo[kind, value] = getattr(self, "_" + kind)(value)
        return got

    def _email(self, v: str) -> str:
        local, _, domain = v.rpartition("@")
        host, _, top = domain.rpartition(".")
        return f"{self.k.text(local + '@' + host, 'email')}.{top}"

    def _phone(self, v: str) -> str:
        m = re.match(r"\+\d{1,3}(?=[ .(-])|0", v)  # the country, or the national prefix, stays as part of the format
        keep = m.end() if m else 0
        return v[:keep] + self.k.text(v[keep:], "phone" + v[:keep])

    def _card(self, v: str) -> str:
        at = max(i for i, c in enumerate(v) if c.isdigit())
        body = v[0] + self.k.text(v[1:at], "card" + v[0])
        digits = "".join(c for c in body if c.isdigit())
        return body + str(-luhn(digits + "0") % 10) + v[at + 1 :]

    def _ssn(self, v: str) -> str:
        return self.k.text(v, "ssn")

    def _iban(self, v: str) -> str:
        body = self.k.text(v[4:], "iban" + v[:2])
        plain = body.replace(" ", "") + v[:2] + "00"
        return f"{v[:2]}{98 - int(''.join(str(int(c, 36)) for c in plain)) % 97:02d}{body}"

    def _ip(self, v: str) -> str:
        x = 0
        for p in v.split("."):
            x = x * 256 + int(p)
        y = self.k.step(x, 1 << 32, "ip")
        return ".".join(str(y >> s & 255) for s in (24, 16, 8, 0))

    def _ip6(self, v: str) -> str:
        return self.k.text(v, "ip6", _hex)

    def _secret(self, v: str) -> str:
        if _is_hex(v):
            return self.k.text(v, "hex", _hex)
        while _is_hex(v := self.k.text(v, "secret")):  # on to a value that isn't taken for the other class
            pass
        return v

    def _initial(self, v: str) -> str:
        return self.k.text(v, "initial")

    def _forename(self, v: str) -> str:
        """A forename of no list keeps its last letter, which often carries gender."""
        out = v
        while (out := self.k.text(out[:-1], "forename" + v[-1]) + v[-1]) in _given and out != v:
            pass
        return out

    def _given(self, v: str) -> str:
        names, i = _given[v]
        return names[self.k.step(i, len(names), "given" + names[0])]

    def _surname(self, v: str) -> str:
        end = _ending(v)
        out = v
        while True:  # on along the cycle past values that are given names or belong to another ending
            out = self.k.text(out[: len(out) - len(end)], "name" + end) + end
            if out == v or (out not in _given and _ending(out) == end):
                return out


def find(text: str) -> list[tuple[int, int, str]]:
    """Spans ``(start, end, kind)`` that don't overlap, in order."""
    spans: list[tuple[int, int, str]] = []
    if "@" in text:
        spans += [(*m.span(), "email") for m in EMAIL.finditer(text)]
    spans += [(*m.span(2 if m[2] else 3), "secret") for m in SECRET.finditer(text)]
    if text.count(":") > 1:
        for m in V6.finditer(text):
            v = m[0]
            try:
                ipaddress.IPv6Address(v)
            except ValueError:
                continue
            if any(c != ":" for c in v) and (v.count(":") > 3 or any(c.isdigit() for c in v) and len(v) > 5):
                spans.append((*m.span(), "ip6"))
    if "先生" in text or "女士" in text or "小姐" in text or "さん" in text or "様" in text:
        spans += [(*m.span(), "surname") for m in EAST.finditer(text)]
    if _digit(text):
        for m in NUMBER.finditer(text):
            v = m[0]
            digits = re.sub(r"\D", "", v)
            if re.fullmatch(r"\d+(\.\d+){3}", v):
                if all(int(p) < 256 and str(int(p)) == p for p in v.split(".")):
                    spans.append((*m.span(), "ip"))
            elif re.fullmatch(r"0\d{2,4}[ -]\d{3,4}[ -]?\d{3,4}", v):
                if 10 <= len(digits) <= 12:
                    spans.append((*m.span(), "phone"))
            elif v[0] == "+" or v[0] == "(" or re.fullmatch(r"\d{3}[.-]\d{3}[.-]\d{4}", v):
                if 7 <= len(digits) <= 15:
                    spans.append((*m.span(), "phone"))
            elif re.fullmatch(r"\d{3}-\d{2}-\d{4}", v):
                spans.append((*m.span(), "ssn"))
            elif 13 <= len(digits) <= 19 and luhn(digits) == 0 and len(set(digits)) > 1:
                spans.append((*m.span(), "card"))
        spans += [(*m.span(), "iban") for m in IBAN.finditer(text) if iban_ok(m[0])]
    if _hint(text):
        surnames = set()
        for m in NAME.finditer(text):
            two = m[3] and m[4]  # after a title the first of two names is a forename
            for i in range(1, 9):
                if m[i]:
                    kind = "initial" if i in _INITIAL else "given" if m[i] in _given else "forename" if i in _FIRST and two else "surname"
                    surnames |= {m[i]} if kind == "surname" else set()
                    spans.append((*m.span(i), kind))
        if surnames:
            bare = re.compile(r"\b(?:" + "|".join(sorted(map(re.escape, surnames), key=len, reverse=True)) + r")\b")
            spans += [(*m.span(), "surname") for m in bare.finditer(text)]
    out: list[tuple[int, int, str]] = []
    for s in sorted(set(spans), key=lambda s: (s[0], -s[1])):
        if not out or s[0] >= out[-1][1]:
            out.append(s)
    return out


def replace(text: str | None, to: Surrogates) -> tuple[str | None, list[tuple[str, str, str]]]:
    """The text with surrogates, and ``(kind, value, surrogate)`` of each entity in order."""
    if not text:
        return text, []
    out, at, made = [], 0, []
    for start, end, kind in find(text):
        value = text[start:end].lower() if kind == "ip6" else text[start:end]  # one address, whichever case its digits have
        new = to.of(kind, value)
        made.append((kind, value, new))
        out += [text[at:start], new]
        at = end
    return ("".join([*out, text[at:]]) if made else text), made


_loaded: dict[bytes, Surrogates] = {}


def _with(key: bytes) -> Surrogates:
    return _loaded.setdefault(key, Surrogates(key))


def _passed(docs: DataFrame, key: bytes) -> DataFrame:
    """``doc_id, n_entities, kinds, text, found`` of every row, found being the distinct entities as ``kind, value, surrogate`` by keyed hashes."""

    def run(batches):
        to = _with(key)
        common.claim("surrogates", to.memo.clear)
        mark = lambda v: int.from_bytes(hashlib.blake2b(v.encode("utf-8", "surrogatepass"), key=key[:64], digest_size=8).digest(), "big", signed=True)
        for batch in batches:
            for part in common.slices(batch, 64):
                made = [replace(t, to) for t in part.column(1).to_pylist()]
                kinds = [sorted(k for k, _, _ in m) for _, m in made]
                found = [[{"kind": k, "value": mark(v), "surrogate": mark(s)} for k, v, s in sorted(set(m))] for _, m in made]
                yield pa.record_batch([part.column(0), pa.array([len(m) for _, m in made], pa.int64()), pa.array(kinds, pa.list_(pa.string())), pa.array([t for t, _ in made], pa.string()), pa.array(found, pa.list_(pa.struct([("kind", pa.string()), ("value", pa.int64()), ("surrogate", pa.int64())])))], ["doc_id", "n_entities", "kinds", "text", "found"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return common.arrow_map(rows, run, "doc_id long, n_entities long, kinds array<string>, text string, found array<struct<kind:string,value:long,surrogate:long>>")


def surrogates(docs: DataFrame, key: bytes) -> DataFrame:
    """``doc_id, n_entities, kinds, text`` of every row, the text with surrogates; one narrow pass."""
    return _passed(docs, key).drop("found")


def checked(docs: DataFrame, key: bytes) -> DataFrame:
    """``surrogates`` and the corpus-wide check: ``n_collisions``, a document's entities whose surrogate stands for another value too, anywhere.

    The texts are written once; what is compared are keyed hashes of the distinct entities, pre-aggregated before they are shuffled.
    """
    done = common.written(_passed(docs, key), "surrogates")
    each = done.select(F.explode("found").alias("x")).select("x.*").distinct()
    bad = common.written(each.groupBy("kind", "surrogate").agg(F.count("*").alias("n")).where("n > 1").select("kind", "surrogate"), "collisions")
    out = done.drop("found")
    if bad.isEmpty():
        return out.withColumn("n_collisions", F.lit(0).cast("long"))
    where = done.select("doc_id", F.xxhash64("text").alias("h"), F.explode("found").alias("x")).select("doc_id", "h", "x.kind", "x.surrogate")
    hits = where.join(common.small_side(bad), ["kind", "surrogate"], "left_semi").groupBy("doc_id", "h").agg(F.count_distinct("kind", "surrogate").alias("n_collisions"))
    same = out["doc_id"].eqNullSafe(hits["doc_id"]) & F.xxhash64(out["text"]).eqNullSafe(hits["h"])
    return out.join(hits, same, "left").select(out["doc_id"], "n_entities", "kinds", "text", F.coalesce("n_collisions", F.lit(0)).cast("long").alias("n_collisions"))


def entities(docs: DataFrame, key: bytes) -> DataFrame:
    """``doc_id, kind, value, surrogate`` of every mention."""

    def run(batches):
        to = _with(key)
        common.claim("surrogates", to.memo.clear)
        for batch in batches:
            for part in common.slices(batch, 64):
                rows = [(i, *m) for i, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True) for m in replace(t, to)[1]]
                cols = list(zip(*rows, strict=True)) or [(), (), (), ()]
                yield pa.record_batch([pa.array(c, pa.int64() if i == 0 else pa.string()) for i, c in enumerate(cols)], ["doc_id", "kind", "value", "surrogate"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return common.arrow_map(rows, run, "doc_id long, kind string, value string, surrogate string")


def collisions(docs: DataFrame, key: bytes) -> DataFrame:
    """Surrogates that stand for more than one value of a kind: empty, unless something is wrong."""
    pairs = entities(docs, key).select("kind", "value", "surrogate").distinct()
    return pairs.groupBy("kind", "surrogate").agg(F.count("*").alias("n")).where("n > 1")
