"""Personal data: patterns propose spans, validators confirm them, nearby words adjust the score.

Every kind has a pattern, a validator and a base score. A span is kept if its validator
accepts it and its score reaches the threshold. Kinds of the base list start at the
threshold, so context can only raise them. Further kinds need a checksum (mod 97), a stated
frame (private keys), or start below it and need a context word close by (secrets by their
entropy, social security numbers).

Matches are the leftmost ones that do not overlap, per kind; a match that fails is
dropped without a second try. Positions are code points, the end exclusive.

Defined cases: null is empty; repeated rows come back once each; an empty table gives an
empty result; long texts are searched whole.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BASE = ("email", "ip", "card", "phone")
# The base patterns, in forms that take time in proportion to the text: an address is
# grown around its "@", digit runs are entered at their first digit only.
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"(?<![0-9])[0-9]+(?:\.[0-9]+){3}")
CARD = re.compile(r"[0-9]+(?:[\x20-][0-9]+)*")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")

IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
SSN = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
SECRET = re.compile(r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/=-]{20,}")
PRIVATE = re.compile(r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----")
#: Bits a character that a secret has at least; words and numbers in a row have fewer, random hexadecimal digits about 3.7.
ENTROPY = 3.0
#: How far, in code points, a context word may stand before or behind a span.
REACH = 40
THRESHOLD = 0.5


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def mod97(code: str) -> bool:
    """ISO 7064 mod 97-10 over a rearranged account number."""
    code = code.replace(" ", "")
    return 15 <= len(code) <= 34 and int("".join(str(int(c, 36)) for c in code[4:] + code[:4])) % 97 == 1


def only_digits(s: str) -> str:
    return re.sub("[^0-9]", "", s)


def _card(s: str) -> bool:
    d = only_digits(s)
    return 16 <= len(d) <= 19 and luhn(d)


def _ip(s: str) -> bool:
    return all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or "0") <= 255 for p in s.split("."))


def _ssn(s: str) -> bool:
    a, b, c = s.split("-")
    return a not in ("000", "666") and a < "900" and b != "00" and c != "0000"


def _random(s: str) -> bool:
    """Letters and digits without an order that saves bits."""
    shares = [n / len(s) for n in Counter(s).values()]
    return any(c.isdigit() for c in s) and any(c.isalpha() for c in s) and -sum(p * math.log2(p) for p in shares) >= ENTROPY


@dataclass(frozen=True)
class Kind:
    name: str
    pattern: re.Pattern
    valid: Callable[[str], bool]
    score: float
    #: A match must hold this text; without it the search ends at once.
    needs: str = ""
    context: frozenset = field(default_factory=frozenset)
    boost: float = 0.35


KINDS = (
    Kind("email", DOMAIN, lambda s: True, 0.9, "@", frozenset({"email", "e-mail", "mail", "contact"})),
    Kind("ip", IP, _ip, 0.6, ".", frozenset({"ip", "host", "server", "address"})),
    Kind("card", CARD, _card, 0.8, "", frozenset({"card", "visa", "credit", "mastercard"})),
    Kind("phone", PHONE, lambda s: 8 <= len(only_digits(s)) <= 15, 0.6, "+", frozenset({"phone", "tel", "call", "mobile", "fax"})),
    Kind("iban", IBAN, mod97, 0.7, "", frozenset({"iban", "account", "bank"})),
    Kind("ssn", SSN, _ssn, 0.3, "-", frozenset({"ssn", "social", "security"})),
    Kind("secret", SECRET, _random, 0.3, "", frozenset({"token", "secret", "password", "passwd", "api", "apikey", "key", "auth", "bearer", "credential"})),
    Kind("private_key", PRIVATE, lambda s: True, 0.9, "-----BEGIN "),
)
_WORD = re.compile(r"[a-z-]+")


def _addresses(text: str) -> Iterator[tuple[int, int]]:
    """Mail addresses: from the first local character behind the last "@" or match, to the end of the domain."""
    floor, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in LOCAL:
            start -= 1
        floor = at + 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            floor = m.end()
            yield start, floor
        at = text.find("@", floor)


def _matches(kind: Kind, text: str, lower: str) -> Iterator[tuple[int, int]]:
    """Where a kind's pattern matches; nothing where its spans could not reach the threshold."""
    if kind.needs not in text or kind.score < THRESHOLD and not any(w in lower for w in kind.context):
        return iter(())
    return _addresses(text) if kind.pattern is DOMAIN else (m.span() for m in kind.pattern.finditer(text))


def find_spans(text: str | None, kinds: tuple[Kind, ...] = KINDS) -> list[tuple[str, int, int, float]]:
    """(kind, start, end, score), by kind as listed and then start."""
    text, out = text or "", []
    lower = text.lower()
    for kind in kinds:
        for start, end in _matches(kind, text, lower):
            if kind.valid(text[start:end]):
                near = (text[max(0, start - REACH) : start] + " " + text[end : end + REACH]).lower()
                score = min(1.0, kind.score + kind.boost * (not kind.context.isdisjoint(_WORD.findall(near))))
                if score >= THRESHOLD:
                    out.append((kind.name, start, end, score))
    return out


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, found array<struct<kind, start, end, score>>."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
        for b in batches:
            found = [[dict(zip(("kind", "start", "end", "score"), s)) for s in find_spans(t.as_py())] for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, kind)], names=[id_col, "found"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(text_col).alias("__text")).mapInArrow(work, f"`{id_col}` {kind}, found array<struct<kind: string, start: bigint, end: bigint, score: double>>")


def redacted(text: str | None, kinds: tuple[Kind, ...] = KINDS) -> str | None:
    """The text with each span, or union of overlapping spans, replaced by the name of its first kind."""
    spans = sorted((s, -e, k) for k, s, e, _ in find_spans(text, kinds))
    if not spans:
        return text
    parts, at, i = [], 0, 0
    while i < len(spans):
        start, end, kind = spans[i][0], -spans[i][1], spans[i][2]
        while i < len(spans) and (spans[i][0] < end or spans[i][0] == start):
            end, i = max(end, -spans[i][1]), i + 1
        parts += [text[at:start], f"<{kind.upper()}>"]
        at = end
    return "".join([*parts, text[at:]])


def redact(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with personal data replaced in ``text_col``; all rows and columns stay."""
    at = docs.columns.index(text_col)
    slots = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.set_column(at, b.schema.field(at), pa.array([redacted(t.as_py()) for t in b.column(at)], b.schema.field(at).type))

    return docs.mapInArrow(work, slots)


def op5(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    out = detect(load_table(spark, sf_dir, "documents"))
    place = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    base = F.filter("found", lambda s: s["kind"].isin(*BASE))
    count = lambda k: F.size(F.filter("found", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    return out.select(
        "doc_id", *[count(k) for k in BASE], F.size("found").cast("long").alias("n_spans"),
        F.sha2(F.array_join(F.transform(base, place), ",").cast("binary"), 256).alias("base_sha256"),
        F.array_join(F.transform("found", place), ",").alias("spans"),
    )
