"""PII surrogates: keyed, of the same type, gender, script and format, distinct for distinct entities and the same for the same one.

Detected: e-mail addresses, telephone numbers, IPv4 addresses, payment-card numbers (13 to 19 digits whose check digit holds), IBANs whose check holds, US social security
numbers, secrets (runs of 32 or more hexadecimal digits, and common token prefixes) and persons after a form of address.

A surrogate keeps case, digits and punctuation in place and draws the rest from HMAC-SHA256 of the key, type, entity and attempt. It keeps:
a phone's country code and fictional exchange, an address's octet lengths and whether it is private, a card's first digit and check
digit, an IBAN's country and check, a secret's case; e-mails go to reserved example domains, persons keep form of address,
gender of ending and script; Mr. and Mrs. of one name are two persons, a Dr. is the only one of them or a third. All distinct entities of the corpus are then compared: a surrogate that two have, or that is an
entity of the corpus, stays with none but the first, and the others draw again, in rounds over written tables until none is left.
Where many entities share a small format, later rounds draw from more: longer locals, names and phones, all octets, then all addresses.

Results for odd input: null and empty texts stay; texts without entities stay as they are; repeated rows repeat; overlapping finds go to the
earlier, then longer one; an empty table gives an empty one; other columns pass unread, whatever their names.
"""

from __future__ import annotations

import hashlib
import hmac
import itertools
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpart.llm.common import give_back, mapped, materialise, portions

#: The session's setting that names the key; without it surrogates follow from a key that is no secret, fit for tests only.
KEY_SETTING, KEY = "spark.blockpart.pii.key", b"surrogates"
#: Rounds in the entity's own format, and rounds until what that format fixes beyond its type is given up too.
NARROW, WIDE = 4, 16
#: Forms of address and the gender that they tell, by script-independent plain text: fixed values.
ADDRESS = {"Mr.": "m", "Mr": "m", "Mrs.": "f", "Mrs": "f", "Ms.": "f", "Ms": "f", "Miss": "f", "Dr.": "n", "Prof.": "n", "Herr": "m", "Frau": "f", "Monsieur": "m", "Madame": "f", "Señor": "m", "Señora": "f", "Господин": "m", "Госпожа": "f"}
_NAME = r"[^\W\d_a-zà-öø-ÿа-я][\w'’-]+"
PATTERNS = {
    "email": r"(?<![\w.+-])[A-Za-z0-9][\w.+-]*@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}",
    "secret": r"(?<![0-9A-Za-z])(?:[0-9a-fA-F]{32,}|(?:AKIA|ASIA)[0-9A-Z]{16}|gh[pousr]_[0-9A-Za-z]{36}|sk-[0-9A-Za-z]{20,})(?![0-9A-Za-z])",
    "iban": r"(?<![0-9A-Za-z])[A-Z]{2}\d{2}(?: ?[0-9A-Z]{4}){2,7}(?: ?[0-9A-Z]{1,3})?(?![0-9A-Za-z])",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "phone": r"(?<![\w+])(?:\+1[ .-]?\(?\d{3}\)?[ .-]?\d{3}[ .-]?\d{4}|\+(?!1\b)\d{1,3}[ .-]?(?:\(\d{1,4}\)|\d{1,4})(?:[ .-]?\d{2,4}){2,4}|\(\d{3}\) ?\d{3}[ .-]\d{4}|\d{3}[.-]\d{3}[.-]\d{4})(?!\d)",
    "ipv4": r"(?<![\d.])(?:25[0-5]|2[0-4]\d|1?\d?\d)(?:\.(?:25[0-5]|2[0-4]\d|1?\d?\d)){3}(?!\.?\d)",
    "card": r"(?<![\d-])\d(?:[ -]?\d){12,18}(?![\d-])",
    "person": r"(?<!\w)(?:" + "|".join(re.escape(a) for a in sorted(ADDRESS, key=len, reverse=True)) + rf") {_NAME}(?: {_NAME})?",
}
IBAN = re.compile(r"[A-Z]{2}\d{2}(?: ?[0-9A-Z]{4}){2,7}(?: ?[0-9A-Z]{1,3})?")
FIND = re.compile("|".join(f"(?P<{k}>{v})" for k, v in PATTERNS.items()))
#: What a text with an entity must hold.
HINT = r"[0-9@]|\b(Mr|Mrs|Ms|Miss|Dr|Prof|Herr|Frau|Monsieur|Madame|Señor|Señora|Господин|Госпожа)\b"
QUICK = re.compile(HINT)


def is_card(text: str, a: int, b: int) -> bool:
    """Whether a card number stands from a to b: 13 digits or more, no digit or hyphen after it, check digit right."""
    return "0" <= text[b - 1] <= "9" and not re.match(r"[\d-]", text[b : b + 1]) and len(digits := re.sub(r"\D", "", text[a:b])) >= 13 and luhn(digits)


def is_iban(text: str, a: int, b: int) -> bool:
    return not re.match("[0-9A-Za-z]", text[b : b + 1]) and IBAN.fullmatch(text, a, b) is not None and mod97(text[a:b].replace(" ", ""))


#: Types with check digits: the longest part of a match that holds them counts.
CHECKED = {"card": is_card, "iban": is_iban}


def find(text: str) -> Iterator[tuple[int, int, str]]:
    """(first, end, type) of each entity, in order."""
    if QUICK.search(text):
        at = 0
        while m := FIND.search(text, at):
            (a, b), kind = m.span(), m.lastgroup
            if kind in CHECKED:
                b = next((k for k in range(b, a, -1) if CHECKED[kind](text, a, k)), a)
            # Nothing that holds its check begins here: another entity may begin inside.
            if b > a:
                yield a, b, kind
            at = max(b, a + 1)


def canonical(kind: str, entity: str) -> str:
    """What makes two mentions one entity: digits without separators, lower-case addresses, names without the form of address."""
    if kind == "email":
        return entity.lower()
    if kind in ("phone", "card", "ssn"):
        return re.sub(r"[^\d+]", "", entity)
    if kind == "iban":
        return entity.replace(" ", "")
    if kind == "person":
        return entity.split(" ", 1)[1]
    return entity


class Draw:
    """Numbers from HMAC-SHA256, as many as asked for."""

    def __init__(self, key: bytes, *what: object):
        self.key, self.what, self.block, self.raw = key, "|".join(map(str, what)).encode(), 0, b""

    def __call__(self, n: int) -> int:
        if len(self.raw) < 4:
            self.raw += hmac.new(self.key, self.what + b"|%d" % self.block, hashlib.sha256).digest()
            self.block += 1
        value, self.raw = int.from_bytes(self.raw[:4]), self.raw[4:]
        return value * n >> 32


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (2 if k % 2 else 1)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def mod97(iban: str) -> bool:
    return int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97 == 1


def like(text: str, draw: Draw) -> str:
    """Every ASCII letter and digit anew, of the same kind."""
    out = []
    for c in text:
        if "0" <= c <= "9":
            out.append(chr(48 + draw(10)))
        elif "a" <= c <= "z":
            out.append(chr(97 + draw(26)))
        elif "A" <= c <= "Z":
            out.append(chr(65 + draw(26)))
        else:
            out.append(c)
    return "".join(out)


#: Syllables for names by script, and endings by gender: fixed values.
SYLLABLES = {"latin": ("ka", "lo", "mi", "ra", "ten", "do", "bel", "sa", "nor", "vi", "gar", "le", "tu", "fen", "cor", "pa"), "cyrillic": ("ка", "ло", "ми", "ра", "тен", "до", "бел", "са", "нор", "ви", "гар", "ле", "ту", "фен", "кор", "па"), "greek": ("κα", "λο", "μι", "ρα", "τεν", "δο", "βελ", "σα", "νορ", "βι", "γαρ", "λε", "του", "φεν", "κορ", "πα")}
ENDINGS = {"latin": {"m": "o", "f": "a", "n": "e"}, "cyrillic": {"m": "ов", "f": "ова", "n": "ин"}, "greek": {"m": "ος", "f": "α", "n": "ης"}}


def script(word: str) -> str:
    c = next((x for x in word if x.isalpha()), "a")
    return "cyrillic" if "Ѐ" <= c <= "ԯ" else "greek" if "Ͱ" <= c <= "Ͽ" else "latin"


def name_like(word: str, gender: str, draw: Draw, more: int = 0) -> str:
    kind = script(word)
    made = "".join(SYLLABLES[kind][draw(16)] for _ in range(max(2, min(5, len(word) // 2)) + more)) + ENDINGS[kind][gender]
    return made.upper() if word.isupper() and len(word) > 1 else made.capitalize()


def surrogate(kind: str, entity: str, gender: str, attempt: int, key: bytes = KEY) -> str:
    """The stand-in of a canonical entity, in canonical form. Later attempts draw from larger spaces."""
    draw = Draw(key, kind, entity, attempt)
    more, wide = attempt // NARROW, attempt >= WIDE
    if kind == "email":
        local, _, domain = entity.partition("@")
        labels = domain.split(".")
        ending = ("com", "net", "org")[Draw(key, "domain", domain, 0)(3)]
        host = [like(x, Draw(key, "domain", domain, k)) for k, x in enumerate(labels[:-2])]
        return f"{like(local + 'x' * more, draw)}@{'.'.join([*host, 'example', ending])}"
    if kind == "phone":
        head = re.match(r"\+1|\+\d{2}|", entity)[0]
        rest = entity[len(head) :]
        # Numbers with another country code may get longer; those of ten digits have room.
        new = "".join(str(draw(10)) for _ in range(len(rest) + (attempt // WIDE if head != "+1" and head else 0)))
        return head + (new[:3] + "555" + new[6:] if len(rest) == 10 and rest[3:6] == "555" and not wide else new)
    if kind == "ssn":
        return (str(draw(10)) if wide else "9") + "".join(str(draw(10)) for _ in entity[1:])
    if kind == "card":
        while True:
            new = (str(draw(10)) if wide else entity[0]) + "".join(str(draw(10)) for _ in entity[1:])
            if luhn(new) == luhn(entity):
                return new
    if kind == "iban":
        body = "".join("0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"[draw(36)] for _ in entity[4:]) if wide else like(entity[4:], draw)
        number = int("".join(str(int(c, 36)) for c in body + entity[:2] + "00"))
        return f"{entity[:2]}{98 - number % 97:02d}{body}"
    if kind == "ipv4":
        parts = entity.split(".")
        fixed = 1 if parts[0] in ("10", "127") else 2 if parts[:2] == ["192", "168"] or parts[0] == "172" and 16 <= int(parts[1]) <= 31 else 0
        ranges = {1: (1, 9), 2: (10, 99), 3: (100, 223)}
        if attempt >= 2 * WIDE:
            return ".".join(str(draw(256)) for _ in range(4))
        if attempt >= NARROW:
            # All octets; a private network may become the largest one. Public addresses stay outside of networks told by their first octets.
            public = [k for k in range(1, 224) if k not in (10, 127, 172, 192)]
            out = ["10"] if wide and fixed == 2 else parts[:fixed] or [str(public[draw(len(public))])]
            return ".".join([*out, *(str(draw(256)) for _ in range(4 - len(out)))])
        out = parts[:fixed]
        for k in range(fixed, 4):
            low, high = ranges[len(parts[k])]
            out.append(str(low + draw((high if k == 0 or len(parts[k]) < 3 else 254) - low + 1)))
        return ".".join(out)
    if kind == "person":
        return " ".join(name_like(w, gender, Draw(key, "name", w, gender, attempt), more) for w in entity.split(" "))
    if re.fullmatch(r"[0-9a-fA-F]+", entity):
        upper = entity.upper() == entity
        return "".join(("0123456789ABCDEF" if upper else "0123456789abcdef")[draw(16)] for _ in entity)
    head = re.match(r"AKIA|ASIA|gh._|sk-", entity)[0]
    return head + like(entity[len(head) :], draw)


def dressed(kind: str, mention: str, stand_in: str) -> str:
    """A stand-in in the format of one mention: its separators, its form of address, its case."""
    if kind in ("phone", "card", "ssn", "iban"):
        letters = iter(stand_in)
        return "".join([*(next(letters) if c.isalnum() or c == "+" else c for c in mention), *letters])
    if kind == "person":
        return f"{mention.split(' ', 1)[0]} {stand_in}"
    if kind == "email":
        return "".join(s.upper() if m.isupper() else s for m, s in zip(mention, stand_in, strict=False)) + stand_in[len(mention) :]
    return stand_in


def gender_of(kind: str, mention: str) -> str:
    return ADDRESS[mention.split(" ", 1)[0]] if kind == "person" else ""


def entities(docs: DataFrame) -> DataFrame:
    """Distinct (text_key, kind, entity, gender) of texts; the key is the MD5 sum of the text."""

    def run(batches):
        for batch in batches:
            rows = []
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                text = text.as_py()
                rows += {(key, k, canonical(k, text[a:b]), gender_of(k, text[a:b])) for a, b, k in find(text)}
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.string()) for c in zip(*sorted(rows), strict=True)], names=["text_key", "kind", "entity", "gender"])

    some = docs.where(F.col("text").rlike(HINT)).select(F.md5("text").alias("text_key"), "text")
    return mapped(some, run, "text_key string, kind string, entity string, gender string").distinct()


def told(found: DataFrame) -> DataFrame:
    """Distinct (kind, entity, gender) and own, the gender of the person meant: Mr. and Mrs. of one name are two; one without a told gender is the only other, if there is one."""
    forms = found.select("kind", "entity", "gender").distinct()
    known = forms.where("kind = 'person' and gender <> 'n'").groupBy("kind", "entity").agg(F.min("gender").alias("low"), F.max("gender").alias("high"))
    own = F.when((F.col("gender") == "n") & (F.col("low") == F.col("high")), F.col("low")).otherwise(F.col("gender"))
    return forms.join(known, ["kind", "entity"], "left").select("kind", "entity", "gender", own.alias("own"))


def session_key(spark: SparkSession) -> bytes:
    return spark.conf.get(KEY_SETTING, KEY.decode()).encode()


def assignment(found: DataFrame, key: bytes | None = None) -> DataFrame:
    """kind, entity, gender (as told) and a stand_in that no other entity has and that is no entity, by rounds."""
    key = session_key(found.sparkSession) if key is None else key

    def drawn(frame: DataFrame, attempt: int) -> DataFrame:
        def run(batches):
            for batch in batches:
                yield batch.append_column("stand_in", pa.array([surrogate(*row, attempt, key) for row in zip(*(c.to_pylist() for c in batch.columns), strict=True)], pa.string()))

        return mapped(frame, run, "kind string, entity string, gender string, stand_in string")

    forms = materialise(told(found))
    all_ = materialise(forms.select("kind", "entity", F.col("own").alias("gender")).distinct())
    names = all_.select("kind", F.col("entity").alias("stand_in")).distinct()
    fixed, left = None, all_
    for attempt in itertools.count():
        tried = materialise(drawn(left, attempt))
        free = tried.join(names, ["kind", "stand_in"], "left_anti")
        if fixed is not None:
            free = free.join(fixed.select("kind", "stand_in"), ["kind", "stand_in"], "left_anti")
        won = free.groupBy("kind", "stand_in").agg(F.min(F.struct("entity", "gender")).alias("first")).select("kind", "first.entity", "first.gender", "stand_in")
        fixed = materialise(won if fixed is None else fixed.unionByName(won))
        left = materialise(all_.join(fixed, ["kind", "entity", "gender"], "left_anti"))
        if left.isEmpty():
            return forms.join(fixed.withColumnRenamed("gender", "own"), ["kind", "entity", "own"]).select("kind", "entity", "gender", "stand_in")


def replaced(docs: DataFrame, key: bytes | None = None) -> DataFrame:
    """All rows and columns, with surrogates in the texts; n_replaced (mentions) is added. Without a key that of the session is taken."""
    names = {c: f"_own_{i}" for i, c in enumerate(docs.columns)}
    own = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in names.items()])
    text = names["text"]
    found = materialise(entities(docs))
    table = assignment(found.select("kind", "entity", "gender"), key)
    pairs = found.join(table, ["kind", "entity", "gender"])
    pairs = pairs.groupBy("text_key").agg(F.collect_list(F.struct("kind", "entity", "gender", "stand_in")).alias("_pairs"))
    hint = F.coalesce(F.col(text).rlike(HINT), F.lit(False))
    some = own.where(hint).withColumn("text_key", F.md5(text)).join(pairs, "text_key", "left").drop("text_key")
    places = list(names.values())

    def run(batches):
        at = places.index(text)
        for batch in batches:
            for part in portions(batch, at):
                texts, counts = [], []
                for body, given in zip(part.column(at).to_pylist(), part.column(len(places)), strict=True):
                    stand_in = {(p["kind"], p["entity"], p["gender"]): p["stand_in"] for p in given.as_py() or ()}
                    out, done, n = [], 0, 0
                    for a, b, kind in find(body) if stand_in else ():
                        mention = body[a:b]
                        out += [body[done:a], dressed(kind, mention, stand_in[kind, canonical(kind, mention), gender_of(kind, mention)])]
                        done, n = b, n + 1
                    texts.append("".join([*out, body[done:]]))
                    counts.append(n)
                columns = [pa.array(texts, pa.string()) if i == at else part.column(i) for i in range(len(places))]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(counts, pa.int64())], names=[*places, "_n"])
        give_back()

    schema = ", ".join([*(f"{n} {docs.schema[c].dataType.simpleString()}" for c, n in names.items()), "_n bigint"])
    out = mapped(some.select(*places, "_pairs"), run, schema).unionByName(own.where(~hint).withColumn("_n", F.lit(0).cast("bigint")))
    return out.select(*[F.col(n).alias(c) for c, n in names.items()], F.col("_n").alias("n_replaced" if "n_replaced" not in docs.columns else "n_replaced_"))


def protected(docs: DataFrame, key: bytes | None = None) -> DataFrame:
    """The documents, same columns, with surrogates; n_chars, where it is a column, follows the text."""
    out = replaced(docs, key).select(*[F.col(f"`{c}`") for c in docs.columns])
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("text").isNotNull(), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out
