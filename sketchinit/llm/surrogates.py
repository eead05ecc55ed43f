"""PII replacement by keyed surrogates.

Entities are found by pattern: e-mail addresses, telephone numbers, IPv4
addresses, payment cards, US social security numbers, and names behind a
form of address. Each gets a surrogate that depends on the key and the entity
alone, so one entity has one surrogate everywhere (coreference).

Digits move by a keyed permutation without fixed points inside their format,
so distinct entities stay distinct and none stands for itself; a card's check
digit follows from the others. Names keep script, case and the number of
parts, and given names their gender: a part has one word wherever it stands,
so a full name and a later surname agree. An entity met under several forms
of address has the gender that most of them tell. Addresses keep their form,
and equal domains stay equal.

Words come from keyed hashes. A check over all distinct parts of the corpus
finds words that two parts share, or that are parts of real entities, and
gives those parts a further attempt, until none is left. Words grow with the
number of parts, so that few clash however large the corpus is: what the
driver and the tasks hold of them is bounded by MAX_RETRIED. The genders of
entities that were met under several reach their texts by a join, however many
there are.

Edge cases: null text stays null; empty tables give no rows; repeated rows
give equal rows; all columns pass through but n_entities and entities, which
are replaced.
"""

from __future__ import annotations

import hashlib
import hmac
import math
import re
from bisect import bisect_left
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T

from ..plans.storage import stash

KEY = b"replace-this-key"
MAX_RETRIED = 20_000  # parts with a further attempt that are sent to all executors; more lengthen the words
LEAST = {"given": 3, "family": 4, "local": 5, "domain": 4}  # syllables of words, by role

_DIGIT = re.compile(r"[0-9]")
_EMAIL = re.compile(r"[\w.+-]+@[\w-]+(?:\.[\w-]+)+")
_IP = re.compile(r"(?<![0-9.])(?:(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?![0-9]|\.[0-9])")
_SSN = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
_CARD = re.compile(r"(?<![0-9-])[0-9](?:[ -]?[0-9]){12,18}(?![0-9-])")
_PHONE = re.compile(r"(?<![\w+(.-])(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,4}\)[ .-]?|[0-9]{2,4}[ .-])[0-9]{3,4}[ .-]?[0-9]{3,5}(?![\w-])")
# Forms of address by gender.
TITLES = {"m": ("Mr", "Herr", "Señor", "Sr", "Monsieur", "Г-н"), "f": ("Mrs", "Ms", "Frau", "Señora", "Sra", "Madame", "Mme", "Г-жа"), "n": ("Dr", "Prof")}
_NAME = re.compile(r"\b(" + "|".join(sorted((t for v in TITLES.values() for t in v), key=len, reverse=True)) + r")\.? ((?:[^\W\d_a-zß-ÿа-яα-ω][^\W\d_]+[ -]?){1,3})")
_GENDER = {t: g for g, v in TITLES.items() for t in v}
# Syllables of made-up names by script, and endings by gender.
SYLLABLES = {
    "latin": "ba be bi bo da de di do fa fe fi ga ge go ha he ka ke ki ko la le li lo ma me mi mo na ne ni no ra re ri ro sa se si so ta te ti to va ve vi vo".split(),
    "cyrillic": "ба бе би бо да де ди до ва ве ви га ге го ка ке ки ко ла ле ли ло ма ме ми мо на не ни но ра ре ри ро са се си со та те ти то".split(),
    "greek": "βα βε βι βο γα γε γι δα δε δι δο κα κε κι κο λα λε λι λο μα με μι μο να νε νι νο ρα ρε ρι ρο σα σε σι σο τα τε τι το".split(),
}
ENDINGS = {"latin": {"m": "n", "f": "a", "n": ""}, "cyrillic": {"m": "н", "f": "я", "n": ""}, "greek": {"m": "ς", "f": "α", "n": ""}}


def luhn(digits: str) -> bool:
    total = sum(int(d) if i % 2 == 0 else (int(d) * 2 - 9 if int(d) > 4 else int(d) * 2) for i, d in enumerate(reversed(digits)))
    return total % 10 == 0


def find(text: str | None) -> list[tuple[int, int, str, str]]:
    """Entities (start, end, kind, gender) in order, not overlapping; the kind first listed wins."""
    if not text:
        return []
    got: list[tuple[int, int, str, str]] = []
    if "@" in text:
        got += [(m.start(), m.end(), "email", "") for m in _EMAIL.finditer(text)]
    if _DIGIT.search(text):
        got += [(m.start(), m.end(), "ip", "") for m in _IP.finditer(text)]
        got += [(m.start(), m.end(), "ssn", "") for m in _SSN.finditer(text)]
        got += [(m.start(), m.end(), "card", "") for m in _CARD.finditer(text) if luhn(re.sub(r"\D", "", m[0]))]
        got += [(m.start(), m.end(), "phone", "") for m in _PHONE.finditer(text)]
    if any(t in text for t in _GENDER):
        got += [(m.start(2), m.start(2) + len(m[2].rstrip(" -")), "name", _GENDER[m[1]]) for m in _NAME.finditer(text)]
    rank = {k: i for i, k in enumerate(("email", "ip", "ssn", "card", "phone", "name"))}
    out: list[tuple[int, int, str, str]] = []  # by place; taken entities do not overlap, so only the neighbours matter
    for e in sorted(got, key=lambda e: (rank[e[2]], e[0])):
        i = bisect_left(out, e)
        if (i == 0 or out[i - 1][1] <= e[0]) and (i == len(out) or e[1] <= out[i][0]):
            out.insert(i, e)
    return out


def _number(key: bytes, *parts: str) -> int:
    return int.from_bytes(hmac.new(key, "\0".join(parts).encode("utf-8", "surrogatepass"), hashlib.sha256).digest(), "big")


def permuted(x: int, size: int, key: bytes, tweak: str, back: bool = False) -> int:
    """A keyed permutation of 0..size-1 (or its inverse): balanced Feistel rounds, walking until the result is in range."""
    half = max(1, ((size - 1).bit_length() + 1) // 2)
    mask = (1 << half) - 1
    while True:
        a, b = x >> half, x & mask
        for r in reversed(range(8)) if back else range(8):
            if back:
                a, b = b ^ (_number(key, tweak, str(r), str(a)) & mask), a
            else:
                a, b = b, a ^ (_number(key, tweak, str(r), str(b)) & mask)
        x = (a << half) | b
        if x < size:
            return x


def moved(x: int, size: int, key: bytes, tweak: str) -> int:
    """A keyed permutation without fixed points (for a size over 1): one step on a keyed cycle through all values."""
    return permuted((permuted(x, size, key, tweak) + 1) % size, size, key, tweak, back=True)


def _digits(text: str, key: bytes, kind: str, first: int = 0, last: int = 0) -> str:
    """text with its digits permuted but for the first and last so many; other characters are kept."""
    at = [i for i, c in enumerate(text) if "0" <= c <= "9"]
    places = at[first : len(at) - last]
    if not places:
        return text
    shape = _DIGIT.sub("0", text)
    new = moved(int("".join(text[i] for i in places)), 10 ** len(places), key, f"{kind}:{shape}:{''.join(text[i] for i in at[:first])}")
    out = list(text)
    for i, d in zip(places, f"{new:0{len(places)}d}"):
        out[i] = d
    return "".join(out)


def _word(n: int, script: str, length: int) -> str:
    syl = SYLLABLES[script]
    out = []
    while len(out) < length:
        n, k = divmod(n, len(syl))
        out.append(syl[k])
    return "".join(out)


def _script(word: str) -> str:
    if any("Ѐ" <= c <= "ӿ" for c in word):
        return "cyrillic"
    return "greek" if any("Ͱ" <= c <= "Ͽ" for c in word) else "latin"


class Words:
    """Words of parts: their length by (role, script), and the attempts of parts whose first word clashed."""

    def __init__(self, length: dict[tuple[str, str], int] | None = None, again: dict[tuple[str, str, str], int] | None = None) -> None:
        self.length, self.again = length or {}, again or {}

    def word(self, role: str, script: str, part: str, key: bytes) -> str:
        n = _number(key, role, part, str(self.again.get((role, script, part), 0)))
        return _word(n, script, self.length.get((role, script), LEAST[role]))


def name_parts(entity: str) -> list[tuple[str, str, str]]:
    """(role, script, part) of a name's words: the first of several is a given name, the others are family names."""
    words = [w for w in re.split(r"[ -]", entity) if w]
    return [("given" if i == 0 and len(words) > 1 else "family", _script(w), w.lower()) for i, w in enumerate(words)]


def parts_of(kind: str, entity: str) -> list[tuple[str, str, str]]:
    """(role, script, part) of all parts of an entity that get words."""
    if kind == "name":
        return name_parts(entity)
    if kind != "email":
        return []
    local, _, domain = entity.lower().rpartition("@")
    return [("local", "latin", f"{local}@{domain}"), ("domain", "latin", domain)]


def surrogate(entity: str, kind: str, gender: str = "", words: Words | None = None, key: bytes = KEY) -> str:
    """The replacement of one entity; equal for equal arguments."""
    w = words or Words()
    if kind == "email":
        local, _, domain = entity.lower().rpartition("@")
        tail = re.search(r"[._-]?[0-9]+$", local)
        end = _digits(tail[0], key, "tail") if tail else ""
        return f"{w.word('local', 'latin', f'{local}@{domain}', key)}{end}@{w.word('domain', 'latin', domain, key)}.example"
    if kind == "ip":
        value = 0
        for part in entity.split("."):
            value = value << 8 | int(part)
        new = moved(value, 1 << 32, key, "ip")
        return ".".join(str(new >> s & 255) for s in (24, 16, 8, 0))
    if kind == "name":
        parts = iter(name_parts(entity))
        out = []
        for p in re.split(r"([ -])", entity):
            if p in (" ", "-", ""):
                out.append(p)
                continue
            role, script, part = next(parts)
            new = w.word(role, script, part, key) + (ENDINGS[script][gender or "n"] if role == "given" else "")
            out.append(new.upper() if len(p) > 1 and p.isupper() else new.capitalize())
        return "".join(out)
    if kind == "card":  # a valid check digit; the other digits decide it
        body = _digits(entity, key, "card", last=1)
        i = max(i for i, c in enumerate(body) if "0" <= c <= "9")
        return next(c for c in (body[:i] + d + body[i + 1 :] for d in "0123456789") if luhn(re.sub(r"[^0-9]", "", c)))
    country = re.match(r"\+([0-9]{1,3})(?=[ .(-])", entity)
    return _digits(entity, key, kind, len(country[1]) if country else 0)


_ENTITY = "key string, kind string, gender string, entity string"


def text_key(text: Column) -> Column:
    return F.md5(text.cast("binary"))


def entities(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Every name and e-mail address of a text, once a batch: (key, kind, gender, entity), key that of the text. Other kinds need no look at the corpus."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            seen = {(h, k, g, t[s:e]) for h, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()) for s, e, k, g in find(t) if k in ("email", "name")}
            yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.string()) for c in (zip(*sorted(seen)) if seen else ([], [], [], []))], names=["key", "kind", "gender", "entity"])

    return docs.select(text_key(F.col(text_col)).alias("key"), F.col(text_col).alias("text")).mapInArrow(run, _ENTITY)


def voted(found: DataFrame) -> DataFrame:
    """(name, gender) of the names, in lower case, that were met under several genders: the one that most of their forms tell."""
    votes = found.where("kind = 'name'").select("gender", "entity").distinct().groupBy(F.lower("entity").alias("name"))
    n = votes.agg(F.count_if(F.col("gender") == "m").alias("m"), F.count_if(F.col("gender") == "f").alias("f"), F.count_distinct("gender").alias("n"))
    return n.where("n > 1 and m + f > 0").select("name", F.when(F.col("f") >= F.col("m"), "f").otherwise("m").alias("gender"))


def genders_of(found: DataFrame) -> DataFrame:
    """(key, genders) of the texts that hold voted names: pairs of a name and its gender."""
    held = found.where("kind = 'name'").select("key", F.lower("entity").alias("name")).distinct()
    return held.join(voted(found), "name").groupBy("key").agg(F.collect_list(F.struct("name", "gender")).alias("genders"))


def _named(parts: DataFrame, words: Words, key: bytes) -> DataFrame:
    """parts(role, script, part, attempt) with the word of that attempt."""
    size = words.length

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            made = [Words(size, {(r, s, p): a}).word(r, s, p, key) for r, s, p, a in zip(*(b.column(c).to_pylist() for c in ("role", "script", "part", "attempt")))]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(made, pa.string())], names=[*b.schema.names, "made"])

    return parts.select("role", "script", "part", "attempt").mapInArrow(run, "role string, script string, part string, attempt int, made string")


def clashes(parts: DataFrame, words: Words, key: bytes) -> DataFrame:
    """parts(role, script, part, attempt) with `clash`: the word is that of an earlier part of the role, or a real part."""
    made = stash(_named(parts, words, key), "pii")
    nth = F.row_number().over(Window.partitionBy("role", "script", "made").orderBy("attempt", "part"))
    real = parts.select("role", "script", F.col("part").alias("made"), F.lit(True).alias("real"))
    marked = made.withColumn("nth", nth).join(real, ["role", "script", "made"], "left")
    return marked.withColumn("clash", (F.col("nth") > 1) | F.col("real").isNotNull())


def checked(found: DataFrame, key: bytes = KEY, most: int = MAX_RETRIED) -> Words:
    """The words of all parts of found(kind, entity), without clashes."""
    found = found.select("kind", "entity").distinct()

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = sorted({p for k, e in zip(*(b.column(c).to_pylist() for c in ("kind", "entity"))) for p in parts_of(k, e)})
            yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.string()) for c in (zip(*rows) if rows else ([], [], []))], names=["role", "script", "part"])

    parts = stash(found.select("kind", "entity").mapInArrow(split, "role string, script string, part string").distinct(), "pii")
    length = {}
    for r in parts.groupBy("role", "script").count().collect():  # at most four roles in three scripts
        need = math.log(max(1.0, r["count"] ** 2 / 2000)) / math.log(len(SYLLABLES[r["script"]]))  # about a thousand clashes
        length[r["role"], r["script"]] = max(LEAST[r["role"]], math.ceil(need))
    while True:
        words = Words(length)
        state = parts.withColumn("attempt", F.lit(0))
        for attempt in range(1, 12):
            marked = stash(clashes(state, words, key), "pii")
            bad = marked.where("clash").select("role", "script", "part").limit(most + 1).collect()  # checked bound
            if not bad:
                return words
            if len(bad) > most:
                break
            words.again |= {tuple(r): attempt for r in bad}
            state = marked.select("role", "script", "part", F.when(F.col("clash"), F.lit(attempt)).otherwise(F.col("attempt")).cast("int").alias("attempt"))
        length = {k: n + 1 for k, n in length.items()}


def replace(docs: DataFrame, text_col: str = "text", key: bytes = KEY) -> DataFrame:
    """docs with entities in text_col replaced; adds n_entities and entities (kind and the surrogate's place in the new text)."""
    found = stash(entities(docs, text_col), "pii")
    share = docs.sparkSession.sparkContext.broadcast(checked(found, key))
    at = docs.columns.index(text_col)
    names = docs.columns
    several = stash(genders_of(found), "pii").withColumnRenamed("key", "__text_key").withColumnRenamed("genders", "__genders")  # its size is known then, so texts do not move where it is small
    keyed = docs.withColumn("__text_key", text_key(F.col(text_col))).join(several, "__text_key", "left").select(*names, "__genders")
    keep = [c for c in names if c not in ("n_entities", "entities")]
    span = pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = share.value
        for b in batches:
            texts, spans = [], []
            for t, told in zip(b.column(at).to_pylist(), b.column(len(names)).to_pylist()):
                out, done, marks, n = [], 0, [], 0
                most = {r["name"]: r["gender"] for r in told or ()}
                for s, e, kind, gender in find(t):
                    new = surrogate(t[s:e], kind, most.get(t[s:e].lower(), gender) if most else gender, words, key)
                    out += [t[done:s], new]
                    n += s - done
                    marks.append({"kind": kind, "start": n, "end": n + len(new)})
                    n, done = n + len(new), e
                texts.append(t if not out else "".join([*out, t[done:]]))
                spans.append(marks)
            cols = [b.column(i) if i != at else pa.array(texts, pa.string()) for i, c in enumerate(names) if c in keep]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(list(map(len, spans)), pa.int32()), pa.array(spans, pa.list_(span))], names=[*keep, "n_entities", "entities"])

    place = T.StructType([T.StructField("kind", T.StringType()), T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())])
    added = [T.StructField("n_entities", T.IntegerType()), T.StructField("entities", T.ArrayType(place))]
    return keyed.mapInArrow(run, T.StructType([*(docs.schema[c] for c in keep), *added]))
