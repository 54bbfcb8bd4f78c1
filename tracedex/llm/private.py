"""Personal data: detection and surrogate generation (operator 10).

Detected entities are replaced by keyed, type-consistent surrogates of the same format: an entity is read as a
number in the mixed-radix domain of its format (digits stay digits, hex stays hex, octets stay octets, a name
becomes a name of the same gender and script) and moved by a keyed permutation of that domain that has no fixed
point. A permutation keeps distinct entities distinct, and equal entities (in any spelling of one
canonical form) get equal surrogates in every document, without a shuffle or a table of entities. A person found by a title is
replaced at every later or earlier mention of the bare name in the same document as well. `collisions` checks a result of any size for
surrogates that stand for two originals, names among them, and for originals with two surrogates; the query runs it.

Defined cases: null text stays null with no entity; empty text stays empty; repeated rows are treated alike;
other columns pass untouched, also such as are named like ours (`n_entities` and `entities` are replaced).
"""

from __future__ import annotations

import hashlib
import re
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tracedex.llm.common import slices, table

KEY = b"tracedex surrogate key"  # a parameter; keep a real one secret

#: Given names by (gender, script), and family names by script: fixed values that surrogates are drawn from.
GIVEN = {
    ("m", "latin"): "Adam Albert Andreas Anton Carlos Daniel David Eric Felix Frank Georg Hans Henri Hugo Jack James Javier Jean John Jonas Jorge Karl Louis Lucas Luis Marc Martin Michael Miguel Oliver Oscar Paul Peter Pierre Robert Samuel Simon Thomas Victor William".split(),
    ("f", "latin"): "Alice Amelia Anna Beatriz Carla Carmen Caroline Charlotte Clara Claire Elena Elisabeth Emily Emma Eva Greta Hannah Helen Ines Isabel Jane Julia Karin Laura Lena Lucia Maria Marie Marta Mary Nina Olivia Paula Rosa Sarah Sofia Sophie Susan Teresa Victoria".split(),
    ("m", "cyrillic"): "Александр Алексей Андрей Борис Виктор Дмитрий Иван Михаил Николай Павел Пётр Сергей".split(),
    ("f", "cyrillic"): "Анна Вера Галина Елена Ирина Мария Наталья Нина Ольга Светлана Софья Татьяна".split(),
}
FAMILY = {
    "latin": "Alvarez Baker Bauer Becker Bernard Blanc Brown Castro Clark Cooper Dubois Durand Evans Fischer Garcia Girard Hall Hoffmann Jones Keller King Klein Lambert Leroy Lopez Martinez Meyer Moore Moreau Navarro Ortega Parker Richter Romero Roux Schmidt Schneider Smith Torres Weber".split(),
    "cyrillic": "Андреев Белов Волков Егоров Иванов Козлов Лебедев Морозов Новиков Павлов Петров Соколов".split(),
}
TITLES = {"Mr": "m", "Mrs": "f", "Ms": "f", "Miss": "f", "Herr": "m", "Frau": "f", "Monsieur": "m", "Madame": "f", "Señor": "m", "Señora": "f", "Господин": "m", "Госпожа": "f"}

EMAIL = re.compile(r"(?<![\w.+-])[A-Za-z0-9][A-Za-z0-9._%+-]*@[A-Za-z0-9](?:[A-Za-z0-9-]*[A-Za-z0-9])?(?:\.[A-Za-z0-9](?:[A-Za-z0-9-]*[A-Za-z0-9])?)*\.[A-Za-z]{2,}")
PHONE = re.compile(r"\+\d{1,3}[ .-]?\(?\d{2,4}\)?(?:[ .-]?\d{2,4}){2,3}(?!\d)|(?<![\d(])\(\d{3}\) ?\d{3}-\d{4}(?!\d)|(?<![\d.-])\d{3}[-.]\d{3}[-.]\d{4}(?![\d.-]*\d)")
ADDRESS = re.compile(r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)\.){3}(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)(?!\d|\.\d)")
CARD = re.compile(r"(?<![\d-])\d(?:[ -]?\d){12,18}(?![\d-]*\d)")
SOCIAL = re.compile(r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-]*\d)")
ACCOUNT = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
CLOUD_KEY = re.compile(r"(?<![A-Za-z0-9])(?:AKIA|ASIA)[A-Z0-9]{16}(?![A-Za-z0-9])")
#: A quoted secret ends at its closing quote on the line, any other at white space or at a quote that is not between word characters. No length is too long.
SECRET = re.compile(
    r"(?i:pass(?:word|wd)?|pwd|token|secret|api[_-]?key|access[_-]?key)[\"']?\s{0,3}[=:]\s{0,3}"
    r"(?:\"([^\"\\\n]*+(?:(?:\\.|(?<=\w)\"(?=\w))[^\"\\\n]*+)*+)\"|'([^'\\\n]*+(?:(?:\\.|(?<=\w)'(?=\w))[^'\\\n]*+)*+)'|[\"']?([^\s\"']++(?:(?<=\w)[\"'](?=\w)[^\s\"']++)*+))"
)
SECRET_LEAST = 6
NAMED = re.compile(r"(?<!\w)(" + "|".join(sorted(TITLES, key=len, reverse=True)) + r")(\.? )([A-ZÀ-ÞА-ЯЁ][\wÀ-ÿа-яё]+)(?:( )([A-ZÀ-ÞА-ЯЁ][\wÀ-ÿа-яё]+))?")
#: In lower case; every name of SECRET holds one.
SECRET_CUES = ("pass", "pwd", "token", "secret", "key")


def _round(key: bytes, i: int, value: int, size: int) -> int:
    data = hashlib.blake2b(b"%d:%d" % (i, value), key=key[:64], digest_size=48).digest()
    return int.from_bytes(data, "little") % size


def _feistel(x: int, n: int, key: bytes, backwards: bool) -> int:
    """A keyed bijection of 0..n-1 (unbalanced halves a, b with a*b >= n, walked until inside)."""
    a = max(1, 1 << ((n - 1).bit_length() + 1) // 2)
    b = -(-n // a)
    while True:
        left, right = x % a, x // a
        for i in range(7, -1, -1) if backwards else range(8):
            if i % 2:
                right = (right + (-1 if backwards else 1) * _round(key, i, left, b)) % b
            else:
                left = (left + (-1 if backwards else 1) * _round(key, i, right, a)) % a
        x = right * a + left
        if x < n:
            return x


def move(x: int, n: int, key: bytes) -> int:
    """A keyed permutation of 0..n-1 without fixed points (n >= 2): a step along a keyed cycle over all numbers."""
    if n < 2:
        return x
    step = 1 + int.from_bytes(hashlib.blake2b(b"step", key=key[:64], digest_size=8).digest(), "little") % min(n - 1, 1 << 62)
    return _feistel((_feistel(x, n, key, False) + step) % n, n, key, True)


def _stream(values: list[int], sizes: list[int], key: bytes, i: int) -> list[int]:
    """A number below each of `sizes`, all of them depending on all `values`."""
    own = hashlib.blake2b(b"%d:" % i + b"".join(v.to_bytes(2, "little") for v in values), key=key[:64], digest_size=64).digest()
    wide = hashlib.shake_256(own).digest(4 * len(sizes))
    return [int.from_bytes(wide[4 * k : 4 * k + 4], "little") % s for k, s in enumerate(sizes)]


def _long(values: list[int], sizes: list[int], key: bytes, backwards: bool) -> list[int]:
    """A keyed bijection of long formats, place by place, in time proportional to their length."""
    half = len(values) // 2
    left, right = values[:half], values[half:]
    sign = -1 if backwards else 1
    for i in range(7, -1, -1) if backwards else range(8):
        if i % 2:
            right = [(v + sign * k) % s for v, k, s in zip(right, _stream(left, sizes[half:], key, i), sizes[half:], strict=True)]
        else:
            left = [(v + sign * k) % s for v, k, s in zip(left, _stream(right, sizes[:half], key, i), sizes[:half], strict=True)]
    return left + right


#: Places beyond which numbers outgrow what `_round` can mix (halves of 384 bits).
LONG = 120


def _mixed(values: list[int], sizes: list[int], key: bytes) -> list[int]:
    movable = [k for k, s in enumerate(sizes) if s > 1]
    if len(movable) > LONG:
        some, own = [sizes[k] for k in movable], list(values)
        mid = _long([values[k] for k in movable], some, key, False)
        mid[0] = (mid[0] + 1) % some[0]  # no fixed point: one place differs between the two passes
        for k, v in zip(movable, _long(mid, some, key, True), strict=True):
            own[k] = v
        return own
    x, n = 0, 1
    for v, s in zip(values, sizes, strict=True):
        x, n = x * s + v, n * s
    x, out = move(x, n, key), []
    for s in reversed(sizes):
        x, v = divmod(x, s)
        out.append(v)
    return out[::-1]


LOWER_, UPPER_, DIGIT_, HEX_, BASE32_ = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
#: Letters with marks and Cyrillic ones, small and large.
OTHERS_ = ["".join(chr(c) for c in range(a, z + 1) if chr(c).isalpha()) + more for a, z, more in ((0xDF, 0xFF, ""), (0xC0, 0xDE, ""), (0x430, 0x44F, "ё"), (0x410, 0x42F, "Ё"))]


def reshape(text: str, key: bytes, kind: str, sets: str | None = None) -> str:
    """Characters move within their class (or within `sets`); the format is the classes' sequence and stays."""
    classes = [sets if sets and c in sets else next((s for s in (DIGIT_, LOWER_, UPPER_, *OTHERS_) if c in s), c) for c in text]
    if all(len(s) == 1 for s in classes):  # nothing to move: fall back to letters that depend on the text
        return "".join(LOWER_[b % 26] for b in hashlib.blake2b(text.encode(), key=key[:64], digest_size=min(64, max(8, len(text)))).digest())
    own = hashlib.blake2b(f"{kind}|{[s if len(s) > 1 else '' for s in classes]}".encode(), key=key[:64], digest_size=32).digest()
    moved = _mixed([s.index(c) for s, c in zip(classes, text, strict=True)], [len(s) for s in classes], own)
    return "".join(s[v] for s, v in zip(classes, moved, strict=True))


def luhn(digits: str) -> int:
    """The check digit that follows `digits`."""
    total = sum(d if i % 2 else d * 2 - 9 * (d > 4) for i, d in enumerate(int(c) for c in reversed(digits)))
    return -total % 10


def _digits_into(shape: str, digits: str) -> str:
    turn = iter(digits)
    return "".join(next(turn) if c.isdigit() else c for c in shape)


@lru_cache(100_000)
def surrogate(kind: str, value: str, key: bytes = KEY) -> str:
    """The replacement of an entity; same kind and canonical value, same replacement."""
    if kind == "email":
        local, _, domain = value.lower().partition("@")
        host, _, top = domain.rpartition(".")
        moved = reshape(local + "@" + host, key, kind)
        return f"{moved}.{top}"
    if kind == "phone":
        digits = re.sub(r"\D", "", value)
        code = re.match(r"\+(\d{1,3})", value)
        keep = len(code[1]) if code and (len(code[0]) < 4 or value[len(code[0]) : len(code[0]) + 1] in " .-(") else 0
        own, rest = hashlib.blake2b(b"phone%d" % len(digits[keep:]), key=key[:64], digest_size=32).digest(), digits[keep:]
        high = rest[0] in "23456789"
        sizes = [8 if high else 2, *[10] * (len(rest) - 1)]
        first = int(rest[0]) - 2 if high else int(rest[0])
        moved = _mixed([first, *map(int, rest[1:])], sizes, own + bytes([high]))
        return _digits_into(value, digits[:keep] + str(moved[0] + 2 * high) + "".join(map(str, moved[1:])))
    if kind == "ip":
        parts = value.split(".")
        low, count = {1: 0, 2: 10, 3: 100}, {1: 10, 2: 90, 3: 156}
        own = hashlib.blake2b(b"ip" + bytes(map(len, parts)), key=key[:64], digest_size=32).digest()
        moved = _mixed([int(p) - low[len(p)] for p in parts], [count[len(p)] for p in parts], own)
        return ".".join(str(v + low[len(p)]) for v, p in zip(moved, parts, strict=True))
    if kind == "card":
        digits = re.sub(r"\D", "", value)
        valid = luhn(digits[:-1]) == int(digits[-1])
        own = hashlib.blake2b(b"card%d%d%s" % (len(digits), valid, digits[:1].encode()), key=key[:64], digest_size=32).digest()
        body = digits[1:-1] if valid else digits[1:]
        body = "".join(map(str, _mixed([int(c) for c in body], [10] * len(body), own)))
        return _digits_into(value, digits[0] + body + (str(luhn(digits[0] + body)) if valid else ""))
    if kind == "cloud_key":
        return value[:4] + reshape(value[4:], key, kind, BASE32_ if all(c in BASE32_ for c in value[4:]) else None)
    if kind == "secret":
        return reshape(value, key, kind, HEX_ if all(c in HEX_ for c in value) else None)
    return reshape(value, key, kind)


@lru_cache(20_000)
def _listed(word: str, names: tuple[str, ...], key: bytes, label: str) -> str:
    """A name of the list for a listed name, and for any other a spelling of the same shape outside the list: both one to one."""
    own = hashlib.blake2b(label.encode(), key=key[:64], digest_size=32).digest()
    if word in names:
        return names[move(names.index(word), len(names), own)]
    new = reshape(word, own, label)
    while new in names:  # walking on along the permutation's cycle keeps it one to one
        new = reshape(new, own, label)
    return new


def person(title: str, first: str, last: str | None, key: bytes = KEY) -> tuple[str, str | None]:
    """A person keeps gender and script; a family name alone gets the same surrogate as beside its given name."""
    script = "cyrillic" if re.search("[А-Яа-яЁё]", first) else "latin"
    family = tuple(FAMILY[script])
    if last is None:
        return _listed(first, family, key, f"family {script}"), None
    return _listed(first, tuple(GIVEN[TITLES[title], script]), key, f"given {TITLES[title]} {script}"), _listed(last, family, key, f"family {script}")


def find(text: str) -> list[tuple[int, int, str, str]]:
    """(start, end, kind, surrogate-free value) of entities, left to right, without overlap; longer ones first at a tie.

    Cheap containment tests choose which patterns run at all."""
    found: list[tuple[int, int, str, str]] = []
    if "@" in text:
        found += [(m.start(), m.end(), "email", m[0]) for m in EMAIL.finditer(text)]
    low = text.lower()
    if any(c in low for c in SECRET_CUES):
        for m in SECRET.finditer(text):
            g = m.lastindex or 3
            value = m[g].rstrip(",;.:)]}>") if g == 3 else m[g]  # what closes a clause is not part of it
            if len(value) >= SECRET_LEAST:
                found.append((m.start(g), m.start(g) + len(value), "secret", value))
    if "AKIA" in text or "ASIA" in text:
        found += [(m.start(), m.end(), "cloud_key", m[0]) for m in CLOUD_KEY.finditer(text)]
    if any(d in text for d in DIGIT_):
        for pattern, kind in ((PHONE, "phone"), (ADDRESS, "ip"), (CARD, "card"), (SOCIAL, "social"), (ACCOUNT, "account")):
            for m in pattern.finditer(text):
                if kind == "card" and len(re.sub(r"\D", "", m[0])) not in range(13, 20):
                    continue
                found.append((m.start(), m.end(), kind, m[0]))
    if any(t in text for t in TITLES):
        named = list(NAMED.finditer(text))
        found += [(m.start(), m.end(), "name", m[0]) for m in named]
        if named:
            bare = sorted({m[k] for m in named for k in (3, 5) if m[k] and len(m[k]) > 1}, key=lambda n: (-len(n), n))
            found += [(m.start(), m.end(), "bare_name", m[0]) for m in re.finditer(r"(?<!\w)(?:" + "|".join(map(re.escape, bare)) + r")(?!\w)", text)]
    found.sort(key=lambda x: (x[0], -x[1]))
    out, end = [], 0
    for x in found:
        if x[0] >= end:
            out.append(x)
            end = x[1]
    return out


def replace(text: str, key: bytes = KEY) -> tuple[str, list[tuple[str, str, str]]]:
    """(text with surrogates, [(kind, original, surrogate)])."""
    parts, at, made = [], 0, []
    entities = find(text)
    known: dict[str, str] = {}  # bare name -> its surrogate in this document; a family name goes before a given one
    for _, _, kind, value in entities:
        if kind == "name":
            m = NAMED.fullmatch(value)
            first, last = person(m[1], m[3], m[5], key)
            if last:
                known.setdefault(m[3], first)
            known[m[5] or m[3]] = last or first
    for start, end, kind, value in entities:
        if kind == "name":
            m = NAMED.fullmatch(value)
            first, last = person(m[1], m[3], m[5], key)
            new = m[1] + m[2] + first + (m[4] + last if last else "")
        else:
            new = known[value] if kind == "bare_name" else surrogate(kind, value, key)
        parts += [text[at:start], new]
        at = end
        made.append(("name" if kind == "bare_name" else kind, value, new))
    return "".join([*parts, text[at:]]) if parts else text, made


ENTITY = T.ArrayType(T.StructType([T.StructField("kind", T.StringType()), T.StructField("original", T.StringType()), T.StructField("surrogate", T.StringType())]))


def pseudonymise(docs: DataFrame, key: bytes = KEY, text: str = "text", entities: bool = True) -> DataFrame:
    """`docs` with surrogates in its text; with `entities`, what was replaced beside it."""
    names = [c for c in docs.columns if not entities or c not in ("n_entities", "entities")]
    schema = T.StructType([T.StructField(c, T.StringType()) if c == text else docs.schema[c] for c in names] + ([T.StructField("n_entities", T.LongType()), T.StructField("entities", ENTITY)] if entities else []))
    kind = pa.list_(pa.struct([("kind", pa.string()), ("original", pa.string()), ("surrogate", pa.string())]))

    def run(batches):
        for b in slices(batches, text):
            rows = [(None, []) if t is None else replace(t, key) for t in b.column(text).to_pylist()]
            columns = [pa.array([r[0] for r in rows], pa.string()) if c == text else b.column(c) for c in names]
            if entities:
                columns += [pa.array([len(r[1]) for r in rows], pa.int64()), pa.array([[dict(zip(("kind", "original", "surrogate"), e, strict=True)) for e in r[1]] for r in rows], kind)]
            yield pa.RecordBatch.from_arrays(columns, [*names, *(["n_entities", "entities"] if entities else [])])

    return docs.select(*[F.col(c).cast("string").alias(c) if c == text else F.col(c) for c in names]).mapInArrow(run, schema)


def collisions(found: DataFrame) -> DataFrame:
    """kind, value, n: surrogates that stand for more than one original of a kind, and originals with more than one surrogate. None is
    expected; titled names are compared with their titles. Takes a result of `pseudonymise`."""
    original = F.when(F.col("e.kind") == "email", F.lower("e.original")).otherwise(F.col("e.original"))
    each = found.select(F.explode("entities").alias("e")).select("e.kind", original.alias("original"), "e.surrogate").distinct()
    each = each.filter("kind != 'name' or original rlike '[. ]'")  # one bare word may be the given name of one person and the family name of another
    met = each.groupBy("kind", F.col("surrogate").alias("value")).agg(F.count("*").alias("n")).filter("n > 1")
    return met.unionByName(each.groupBy("kind", F.col("original").alias("value")).agg(F.count("*").alias("n")).filter("n > 1"))


def op10_private_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with surrogates for its personal data, the kinds that were found, and how many collisions the corpus has."""
    found = pseudonymise(table(spark, sf_dir, "documents").select("doc_id", "text"))
    kinds = F.array_join(F.array_sort(F.transform("entities", lambda e: e["kind"])), ",")
    checked = collisions(found).agg(F.count("*").alias("n_collisions"))  # one row
    return found.crossJoin(F.broadcast(checked)).select("doc_id", "n_entities", kinds.alias("kinds"), "text", "n_collisions")
