"""Personal data: patterns propose spans, checksums confirm them, words nearby adjust a score.

Base kinds (email, ip, card, phone) are leftmost non-overlapping matches of their pattern that pass
their validator. A failing match of the base
pattern can hide a number beside another one (a phone number before a card number); the method adds such cards and
phones by stricter patterns with the same validators. Further kinds: ``secret`` (a value after a name like
password or token), ``iban`` (country, two check digits, mod-97; a word after it that looks like a last group is left out) and, where
context words stand within CONTEXT characters before, ``ssn`` and ``phone_local``. A span's score starts from its kind,
rises when its validator has a checksum or a context word is near, and falls where words nearby speak
against it (order, version, ...); added spans need MIN_SCORE, base spans always stay.

Null and empty texts have no spans; repeated rows each are searched; offsets are code points, ends
exclusive; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable

import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession

from doccurate.llm.common import arrow_rows, docs_of, table

CONTEXT, MIN_SCORE = 40, 0.6
# The patterns and bounds of the base kinds.
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
# Added kinds.
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
#: Lengths of the countries' numbers (fixed values).
_IBAN_SIZE = {
    country: size
    for size, countries in {
        15: "NO", 16: "BE", 18: "DK FI FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU MN XK", 21: "CH HR LI LV", 22: "BG BH CR DE GB GE IE ME RS VA",
        23: "AE GI IL IQ OM SO TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "LY PT ST", 26: "IS TR", 27: "BI DJ FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HU LB NI PL SV",
        29: "BR EG PS QA UA", 30: "JO KW MU", 31: "MT SC", 32: "LC", 33: "RU",
    }.items()
    for country in countries.split()
}
_SSN = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
_NEAR_PHONE = re.compile(r"(?<![0-9+(.-])\(?0?[0-9]{2,4}\)?[ ./-][0-9]{3,4}[ ./-]?[0-9]{3,5}(?![0-9-])")
_ONE_CARD = re.compile(r"(?<![0-9])(?:[0-9]{14,19}|[0-9]{4}(?:[ -][0-9]{4}){3})(?![0-9])")
_ONE_PHONE = re.compile(r"\+[0-9]{1,3}[ .-]?(?:\([0-9]{1,4}\)|[0-9]{1,4})(?:[ .-][0-9]{2,5}){2,4}?(?![0-9.-])")
_SECRET = re.compile(r"(?i)\b(?:password|passwd|secret|token|api[_-]?key)\b\s?[=:]\s?[\"']?(?P<value>[A-Za-z0-9+/_-]{12,})")
KINDS = ("email", "ip", "card", "phone", "iban", "ssn", "phone_local", "secret")
_FOR = {
    "email": ("mail", "contact", "write", "address"),
    "ip": ("ip", "host", "server", "address"),
    "card": ("card", "visa", "credit", "carte", "karte", "tarjeta", "payment"),
    "phone": ("phone", "tel", "call", "mobile", "fax", "telefon", "téléphone", "teléfono"),
    "iban": ("iban", "account", "konto", "compte", "cuenta", "bank"),
    "ssn": ("ssn", "social security"),
    "secret": (),
    "phone_local": ("phone", "tel.", "tel:", "mobile", "fax", "telefon", "téléphone", "teléfono"),
}
_AGAINST = ("version", "order no", "invoice no", "isbn", "issn", "part no")
_START = {"email": 0.8, "ip": 0.6, "card": 0.8, "phone": 0.7, "iban": 0.8, "ssn": 0.3, "phone_local": 0.3, "secret": 0.7}

Span = tuple[int, int, str, float]


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(map(int, reversed(digits))):
        total += d if k % 2 == 0 else 2 * d - 9 * (d > 4)
    return total % 10 == 0


def mod97(iban: str) -> bool:
    moved = iban[4:] + iban[:4]
    return int("".join(str(int(c, 36)) for c in moved)) % 97 == 1


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def _emails(text: str):
    """Leftmost matches: the run of local characters before an @, from the last match's end on, then the domain."""
    done, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            done = m.end()
        else:
            done = at + 1
        at = text.find("@", done)


def base_spans(text: str) -> list[tuple[int, int, str]]:
    out = [(a, b, "email") for a, b in _emails(text)] if "@" in text else []
    for m in _IP.finditer(text):
        if all(len(p) <= 3 and int(p or "0") <= 255 for p in (x.lstrip("0") for x in m[0].split("."))):
            out.append((*m.span(), "ip"))
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 14 and 14 <= len(d := _digits(m[0])) <= 19 and luhn(d):
            out.append((*m.span(), "card"))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 10 <= len(_digits(m[0])) <= 15:
                out.append((*m.span(), "phone"))
    return out


def _score(text: str, start: int, kind: str) -> float:
    before = text[max(0, start - CONTEXT) : start].lower()
    return _START[kind] + 0.4 * any(w in before for w in _FOR[kind]) - 0.3 * any(w in before for w in _AGAINST)


def _ibans(text: str):
    """Ends tried at each start: the country's length and all that matches, or, without a known length, all and then shorter tails."""
    at = 0
    while m := _IBAN.search(text, at):
        start, at = m.start(), m.start() + 1
        ends = [m.end(), *(k for k in range(m.end() - 1, start, -1) if text[k] == " ")]
        sized = [(end, text[start:end].replace(" ", "")) for end in ends]
        if size := _IBAN_SIZE.get(text[start : start + 2]):
            sized = [x for x in sized if len(x[1]) == size] + sized[:1]
        for end, number in sized:
            if 15 <= len(number) <= 34 and mod97(number):
                yield start, end
                at = end
                break


def _added(text: str, taken: list[tuple[int, int]]) -> list[Span]:
    found: list[Span] = []
    digit = re.search(r"[0-9]", text) is not None  # only secrets can do without
    for kind, pattern in (("card", _ONE_CARD), ("phone", _ONE_PHONE), ("iban", _IBAN), ("secret", _SECRET), ("ssn", _SSN), ("phone_local", _NEAR_PHONE)):
        if not digit and kind != "secret":
            continue
        for start, end in _ibans(text) if kind == "iban" else (m.span("value" if kind == "secret" else 0) for m in pattern.finditer(text)):
            sure = {
                "card": lambda d: 14 <= len(d) <= 19 and luhn(d),
                "phone": lambda d: 10 <= len(d) <= 15,
            }.get(kind, lambda _: True)(_digits(text[start:end]))
            if sure and not any(a < end and start < b for a, b in taken) and (s := _score(text, start, kind)) >= MIN_SCORE:
                found.append((start, end, kind, min(1.0, s)))
                taken.append((start, end))
    return found


def _place(span: tuple) -> tuple[int, int, int]:
    return span[0], KINDS.index(span[2]), span[1]


def base_and_all(text: str | None) -> tuple[list[Span], list[Span]]:
    """The spans of the base patterns alone, and all spans, added cards and phones among them; in the order of find_spans."""
    if not text:
        return [], []
    base = [(a, b, k, min(1.0, _score(text, a, k))) for a, b, k in base_spans(text)]
    return sorted(base, key=_place), sorted(base + _added(text, [(a, b) for a, b, *_ in base]), key=_place)


def find_spans(text: str | None) -> list[Span]:
    """All spans by start, then kind as in KINDS, each with its score (at most 1)."""
    return base_and_all(text)[1]


def redact(text: str | None, spans: list[Span]) -> str | None:
    """The text with each span, overlapping ones together, replaced by its kind in brackets."""
    out, at = [], 0
    for start, end, kind, _ in spans:
        if start >= at:
            out += [text[at:start], f"[{kind.upper()}]"]
        at = max(at, end)
    return "".join([*out, text[at:]]) if spans else text


def map_texts(docs: DataFrame, make_row: Callable[[int | None, str | None], dict], schema: pa.Schema, ddl: str) -> DataFrame:
    """A row of make_row(doc_id, text) for each row of docs(doc_id, text)."""

    def make():
        return lambda b: (make_row(k, t.as_py()) for k, t in zip(b.column(0).to_pylist(), b.column(1), strict=True))

    return docs_of(docs).mapInArrow(arrow_rows(make, schema, 1024), ddl)


def spans_of(docs: DataFrame) -> DataFrame:
    """doc_id, spans(start, end, kind, score) of every row."""
    span = pa.struct([("start", pa.int32()), ("end", pa.int32()), ("kind", pa.string()), ("score", pa.float64())])

    def row(key, text):
        return {"doc_id": key, "spans": [dict(zip(("start", "end", "kind", "score"), s, strict=True)) for s in find_spans(text)]}

    return map_texts(docs, row, pa.schema([("doc_id", pa.int64()), ("spans", pa.list_(span))]), "doc_id long, spans array<struct<start: int, end: int, kind: string, score: double>>")


def redacted(docs: DataFrame) -> DataFrame:
    """docs with the personal data of ``text`` masked, and ``n_chars``, where there is one, counted anew."""
    schema, names = docs.schema, docs.columns

    def run(batches):
        for b in batches:
            at = b.schema.get_field_index("text")
            texts = pa.array([redact(t.as_py(), find_spans(t.as_py())) for t in b.column(at)], pa.string())
            columns = [texts if k == at else c for k, c in enumerate(b.columns)]
            if "n_chars" in names:
                k = b.schema.get_field_index("n_chars")
                columns[k] = pa.compute.utf8_length(texts).cast(b.column(k).type)
            yield pa.RecordBatch.from_arrays(columns, b.schema.names)

    return docs.mapInArrow(run, schema)


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    def row(key, text):
        base, spans = base_and_all(text)
        told = [f"{k}:{a}:{b}" for a, b, k, _ in base]
        counts = {f"n_{kind}": sum(s[2] == kind for s in base) for kind in KINDS[:4]}
        return {"doc_id": key, **counts, "base_sha256": hashlib.sha256(",".join(told).encode()).hexdigest(), "spans": ",".join(f"{k}:{a}:{b}" for a, b, k, _ in spans)}

    schema = pa.schema([("doc_id", pa.int64()), *((f"n_{k}", pa.int64()) for k in KINDS[:4]), ("base_sha256", pa.string()), ("spans", pa.string())])
    ddl = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"
    return map_texts(table(spark, sf_dir, "documents"), row, schema, ddl)
