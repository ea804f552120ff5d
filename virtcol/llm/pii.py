"""Surrogates for personal data.

Detected entities are replaced by keyed ones of the same type and form: every
letter stays a letter of its script, case and kind (vowel, consonant), digits
stay digits, separators stay, a card keeps whether its check digit is right, an
address its ranges, a name its title and its last letter, which carries gender.
For one key the replacement is a permutation of all entities of one form (a
Feistel network, walked until the form's conditions hold), so equal entities
get equal surrogates everywhere and different ones stay different, without a
table of them.

A surrogate may still be another entity of the corpus, or itself.  All distinct
entities are gathered and checked; those whose surrogate collides try the next
permutation.  The few exceptions are broadcast if they are at most EXCEPTIONS,
else joined to the texts they occur in.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, add_columns, arrow_pass, documents, per_process, row_key, text_or_empty

EXCEPTIONS = 100_000
ATTEMPTS = 8
#: The session setting that holds the secret of the registered query and the pipeline, and what stands in for it where it is unset (tests, demonstrations: anyone could invert those surrogates).
KEY_SETTING, DEMONSTRATION = "spark.virtcol.surrogates.key", "demonstration only"

#: Kinds in the order in which they are looked for; a later one never starts inside an earlier one.
KINDS = {
    "email": r"[A-Za-z0-9](?:[A-Za-z0-9._%+-]{0,62}[A-Za-z0-9_+-])?@[A-Za-z0-9](?:[A-Za-z0-9.-]{0,250}[A-Za-z0-9])?\.[A-Za-z]{2,24}(?![A-Za-z0-9])",
    "key": r"(?<![A-Za-z0-9])AKIA[0-9A-Z]{16}(?![A-Za-z0-9])",
    "secret": r"(?:(?<=password=)|(?<=password = )|(?<=password: )|(?<=passwd=)|(?<=token=)|(?<=token = )|(?<=token = \")|(?<=token=\")|(?<=secret=)|(?<=api_key=))[A-Za-z0-9_+/-]{6,200}",
    "hex": r"(?<![A-Za-z0-9])(?=[0-9a-f]{0,63}[0-9])(?=[0-9a-f]{0,63}[a-f])(?:[0-9a-f]{64}|[0-9a-f]{40}|[0-9a-f]{32})(?![A-Za-z0-9])",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "ip": r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)\.){3}(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)(?![\d]|\.\d)",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "card": r"(?<!\d)(?:\d{4}(?:[ -]?\d{4}){3}|3[47]\d{2}[ -]?\d{6}[ -]?\d{5})(?!\d)",
    "phone": r"(?<![\w+])(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?\d{3,4}[ .-]\d{3,4}|\d{3}[.-]\d{3}[.-]\d{4})(?!\w)|(?<![\w+])\+\d{1,3}(?:[ .-]?\d{2,4}){2,5}(?!\w)",
    "name": r"(?:(?<=\bMr )|(?<=\bMr\. )|(?<=\bMrs )|(?<=\bMrs\. )|(?<=\bMs )|(?<=\bMs\. )|(?<=\bHerr )|(?<=\bFrau )|(?<=\bSeñor )|(?<=\bSeñora )|(?<=\bMonsieur )|(?<=\bMadame )|(?<=\bMme )|(?<=\bгосподин )|(?<=\bгоспожа ))[^\W\d_a-z][^\W\d_]{1,30}(?:[ -][^\W\d_a-z][^\W\d_]{1,30}){0,2}",
}
FINDER = re.compile("|".join(f"(?P<{k}>{p})" for k, p in KINDS.items()))
#: A text without any of these holds no entity.
HINT = re.compile(r"@|AKIA|\d[\d.(): -]{5}|password|passwd|token|secret|api_key|[0-9a-f]{16}|\b[A-Z]{2}\d\d|M[rs]|Herr|Frau|Señor|Monsieur|Madame|Mme|господин|госпожа")

#: Letters that stand in for each other: vowels and consonants of a script, accents apart. Fixed values.
ALPHABETS = ("aeiou", "bcdfghjklmnpqrstvwxyz", "áéíóúàèìòùâêîôûäëïöü", "çñ", "аеёиоуыэюя", "бвгджзйклмнпрстфхцчшщ", "αεηιουω", "βγδζθκλμνξπρστφχψ")
CLASS_OF = {c: a for low in ALPHABETS for a in (low, low.upper()) if len(a) == len(low) for c in a}
HEX_LETTERS = "abcdef"


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def places(kind: str, s: str) -> list[str | None]:
    """The letters each place may take; None where it stays."""
    kept: set[int] = set()
    if kind == "email":
        kept = set(range(s.rindex("."), len(s)))
    elif kind == "key":
        kept = set(range(4))
    elif kind == "iban":
        kept = {0, 1}
    elif kind == "card":
        kept = {0}
    elif kind == "phone" and s[0] == "+":
        kept = set(range(re.match(r"\+\d{1,3}?(?=\D|\d{7,})|\+\d", s).end()))
    hexadecimal = kind in ("secret", "hex") and all(c in "0123456789abcdef" for c in s)
    out: list[str | None] = []
    for i, c in enumerate(s):
        first = kind == "phone" and i and s[i - 1] in " (.-" and i + 1 < len(s) and s[i + 1].isdigit() and c in "23456789"
        last = kind == "name" and (i + 1 == len(s) or not s[i + 1].isalpha())
        if i in kept or last:
            out.append(None)
        elif c in "0123456789":
            out.append("23456789" if first else "123456789" if kind == "ip" and c != "0" and (i == 0 or s[i - 1] == ".") and i + 1 < len(s) and s[i + 1] != "." else "0123456789")
        elif hexadecimal:
            out.append(HEX_LETTERS)
        elif kind == "name":
            out.append(CLASS_OF.get(c))
        elif c.isascii() and c.isalpha():
            out.append("abcdefghijklmnopqrstuvwxyz" if c.islower() else "ABCDEFGHIJKLMNOPQRSTUVWXYZ")
        else:
            out.append(None)
    return out


def fits(kind: str, s: str, was: str) -> bool:
    """Conditions of a form beyond its places."""
    if kind == "ip":
        return all(int(x) <= 255 for x in s.split("."))
    if kind == "card":
        return luhn(re.sub(r"\D", "", s)) == luhn(re.sub(r"\D", "", was))
    return True


def permute(x: int, size: int, key: bytes) -> int:
    """A keyed permutation of range(size): four Feistel rounds on the least even number of bits, walked back into range."""
    half = max(1, ((size - 1).bit_length() + 1) // 2)
    mask = (1 << half) - 1
    while True:
        left, right = x >> half, x & mask
        for r in range(4):
            block = b"".join(hashlib.blake2b(bytes([r, i]) + right.to_bytes(half // 8 + 1, "little"), key=key).digest() for i in range(half // 512 + 1))
            left, right = right, left ^ (int.from_bytes(block, "little") & mask)
        x = (left << half) | right
        if x < size:
            return x


@lru_cache(100_000)
def surrogate(kind: str, s: str, key: bytes, attempt: int = 0) -> str:
    """The entity's replacement; for one attempt and key a permutation of all entities of its kind and form."""
    can = places(kind, s)
    at = [i for i, a in enumerate(can) if a]
    size = 1
    for i in at:
        size *= len(can[i])
    if size < 2:
        return s
    form = "".join(c if a is None else f"<{a}>" for c, a in zip(s, can))
    own = hashlib.blake2b(f"{kind}|{attempt}|{form}".encode(), key=key, digest_size=32).digest()
    x = 0
    for i in at:
        x = x * len(can[i]) + can[i].index(s[i])
    while True:
        x = y = permute(x, size, own)
        out = list(s)
        for i in reversed(at):
            y, d = divmod(y, len(can[i]))
            out[i] = can[i][d]
        if fits(kind, got := "".join(out), s):
            return got


def session_key(spark: SparkSession) -> bytes:
    """The secret of a session: 32 bytes from its setting."""
    return hashlib.blake2b(spark.conf.get(KEY_SETTING, DEMONSTRATION).encode(), digest_size=32).digest()


def entities(text: str) -> list[tuple[str, str, int, int]]:
    """(kind, entity, start, end) in order."""
    return [(m.lastgroup, m[0], m.start(), m.end()) for m in FINDER.finditer(text)] if HINT.search(text) else []


def rewrite(text: str, exceptions: dict, key: bytes) -> tuple[str, int]:
    found = entities(text)
    out, at = [], 0
    for kind, s, a, b in found:
        out += [text[at:a], surrogate(kind, s, key, exceptions.get((kind, s), 0))]
        at = b
    return "".join([*out, text[at:]]), len(found)


def _proposals(entity: DataFrame, key: bytes) -> DataFrame:
    """(kind, entity, attempt) with its surrogate and its form, within which surrogates are permuted."""

    def make():
        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            made = [surrogate(k, s, key, a) for k, s, a in zip(*(b.column(i).to_pylist() for i in range(3)))]
            forms = ["".join(c if a is None else f"<{a}>" for c, a in zip(s, places(k, s))) for k, s in zip(b.column(0).to_pylist(), b.column(1).to_pylist())]
            return pa.RecordBatch.from_arrays([*b.columns, pa.array(made, pa.string()), pa.array(forms, pa.string())], names=["kind", "entity", "attempt", "surrogate", "form"])

        return each

    return arrow_pass(entity.select("kind", "entity", "attempt").repartition("kind", "entity"), "kind string, entity string, attempt int, surrogate string, form string", make)


def occurrences(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(key, kind, entity) of all texts, once per text."""

    def make():
        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            rows = [(k, *x) for k, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()) for x in sorted({e[:2] for e in entities(t)})]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 3, (pa.binary(), pa.string(), pa.string()))], names=["key", "kind", "entity"])

        return each

    return arrow_pass(docs.select(row_key(id_col, text_col), text_or_empty(text_col)), "key binary, kind string, entity string", make)


def collisions(found: DataFrame, scratch: Scratch, key: bytes) -> DataFrame:
    """(kind, entity, attempt) of entities that need another permutation than the first.

    A surrogate may be no entity of the corpus and no other entity's surrogate.  A form that still has collisions after
    ATTEMPTS is crowded, as that of addresses may be: all its entities go back to the first permutation, where surrogates
    differ from each other, though one may be another real entity.  So different entities never get one surrogate.
    """
    every = scratch.keep(found.select("kind", "entity").distinct(), "entities")
    now = scratch.keep(_proposals(every.withColumn("attempt", F.lit(0)), key), "proposals")
    for _ in range(ATTEMPTS):
        taken = now.join(every.select("kind", F.col("entity").alias("surrogate")), ["kind", "surrogate"], "left_semi").select("kind", "entity")
        twice = now.groupBy("kind", "surrogate").agg(F.count("*").alias("n"), F.max(F.struct(F.col("attempt") * -1, "entity")).alias("stays")).where("n > 1")
        clash = now.join(twice, ["kind", "surrogate"]).where(F.col("entity") != F.col("stays.entity")).select("kind", "entity")
        bad = scratch.keep(taken.union(clash).distinct(), "bad")
        if bad.isEmpty():
            return now.where("attempt > 0").select("kind", "entity", "attempt")
        again = now.join(bad, ["kind", "entity"], "left_semi").select("kind", "entity", (F.col("attempt") + 1).alias("attempt"))
        now = scratch.keep(now.join(bad, ["kind", "entity"], "left_anti").unionByName(_proposals(again, key)), "proposals")
    crowded = now.join(bad, ["kind", "entity"], "left_semi").select("kind", "form").distinct()
    return now.join(crowded, ["kind", "form"], "left_anti").where("attempt > 0").select("kind", "entity", "attempt")


def replace(docs: DataFrame, key: bytes, most: int = EXCEPTIONS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with its text rewritten under a secret key (up to 64 bytes) and n_entities.

    Null texts stay null and have 0 entities; texts without entities stay as they are.  Repeated rows are rewritten alike.
    A column n_entities of docs is replaced.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "pii")
    found = scratch.keep(occurrences(docs, id_col, text_col), "found")
    odd = scratch.keep(collisions(found, scratch, key), "exceptions")
    order = [f.name for f in docs.schema.fields if f.name != "n_entities"]
    token = uuid.uuid4().hex
    few = odd.count() <= most
    shared = spark.sparkContext.broadcast({(r[0], r[1]): r[2] for r in odd.collect()} if few else {})
    if few:
        ready = docs.drop("n_entities")
        own = F.lit("")
    else:
        per_text = found.join(odd, ["kind", "entity"]).groupBy("key").agg(F.to_json(F.collect_list(F.array("kind", "entity", F.col("attempt").cast("string")))).alias("__odd"))
        ready = docs.drop("n_entities").withColumn("__key", row_key(id_col, text_col)).join(per_text.withColumnRenamed("key", "__key"), "__key", "left").drop("__key")
        own = F.coalesce("__odd", F.lit(""))

    def make():
        import json

        held = per_process("pii", token, lambda: shared.value)

        def work(texts: list[bytes]) -> list:
            out, counts = [], []
            for t in texts:
                odd, _, text = t.decode("utf-8", "replace").partition("\x00")
                text, n = rewrite(text, {(k, e): int(a) for k, e, a in json.loads(odd)} if odd else held, key)
                out.append(text)
                counts.append(n)
            return [out, counts]

        return work

    done = add_columns(ready.withColumn("__in", F.concat(own, F.lit("\x00"), text_or_empty(text_col))), "__in", "__out string, n_entities int", make, token)
    return done.select(*(F.when(F.col(text_col).isNotNull(), F.col("__out")).alias(c) if c == text_col else F.col(f"`{c}`") for c in order), "n_entities")


def op3_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return replace(documents(spark, sf_dir).select("doc_id", "text"), session_key(spark))
