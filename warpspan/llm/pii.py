"""Personal data in text: patterns propose, checksums confirm, context words weigh.

Every kind has a pattern whose leftmost non-overlapping matches are the
proposals, a validator that drops a proposal for good, and a prior score.
Words near a span raise or lower its score. Spans of the base kinds (e-mail,
IP address, payment card, phone) are always kept; spans of further kinds are
kept from ``threshold`` up.

The patterns are written so that one scan is linear in the text even if it is
one long run of digits or letters: digit runs are entered only at their start
and e-mails are found from their ``@``. A span may have any length.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from warpspan.llm.common import values

BASE_KINDS = ("email", "ip", "card", "phone")
MORE_KINDS = ("iban", "ssn", "secret")
KINDS = BASE_KINDS + MORE_KINDS

SPAN = T.StructType(
    [
        T.StructField("kind", T.StringType()),
        T.StructField("start", T.IntegerType()),
        T.StructField("end", T.IntegerType()),
        T.StructField("score", T.DoubleType()),
    ]
)
_ARROW_SPANS = pa.list_(
    pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64())])
)

# Prior scores, and words that speak for or against a kind.
PRIOR = {"email": 0.8, "ip": 0.6, "card": 0.8, "phone": 0.6, "iban": 0.9, "ssn": 0.4, "secret": 0.4}
FOR_KIND = {
    "email": {"mail", "email", "e-mail", "contact", "write", "reach", "correo"},
    "ip": {"ip", "host", "server", "address", "login", "client"},
    "card": {"card", "visa", "credit", "debit", "mastercard", "amex", "payment", "karte", "carte", "tarjeta"},
    "phone": {"phone", "tel", "call", "mobile", "fax", "cell", "telefon", "sms"},
    "iban": {"iban", "bank", "account", "transfer", "konto", "compte", "cuenta"},
    "ssn": {"ssn", "social", "security", "taxpayer"},
    "secret": {"token", "key", "secret", "password", "passwd", "apikey", "api", "bearer", "credential"},
}
AGAINST_KIND = {
    "email": {"example", "placeholder"},
    "ip": {"version", "release", "section", "chapter"},
    "card": {"isbn", "order", "tracking", "serial"},
    "phone": {"isbn", "serial", "version"},
    "iban": {"isbn", "serial"},
    "ssn": {"isbn", "serial", "part"},
    "secret": {"commit", "sha1", "sha256", "md5", "checksum", "digest"},
}

# Lengths of account numbers by country.
IBAN_LENGTHS = {
    "AD": 24, "AE": 23, "AL": 28, "AT": 20, "AZ": 28, "BA": 20, "BE": 16, "BG": 22, "BH": 22, "BR": 29, "BY": 28, "CH": 21, "CR": 22, "CY": 28, "CZ": 24,
    "DE": 22, "DK": 18, "DO": 28, "EE": 20, "EG": 29, "ES": 24, "FI": 18, "FO": 18, "FR": 27, "GB": 22, "GE": 22, "GI": 23, "GL": 18, "GR": 27, "GT": 28,
    "HR": 21, "HU": 28, "IE": 22, "IL": 23, "IQ": 23, "IS": 26, "IT": 27, "JO": 30, "KW": 30, "KZ": 20, "LB": 28, "LC": 32, "LI": 21, "LT": 20, "LU": 20,
    "LV": 21, "MC": 27, "MD": 24, "ME": 22, "MK": 19, "MR": 27, "MT": 31, "MU": 30, "NL": 18, "NO": 15, "PK": 24, "PL": 28, "PS": 29, "PT": 25, "QA": 29,
    "RO": 24, "RS": 22, "SA": 24, "SC": 31, "SE": 24, "SI": 19, "SK": 24, "SM": 27, "ST": 25, "SV": 28, "TL": 23, "TN": 24, "TR": 26, "UA": 29, "VA": 22,
    "VG": 24, "XK": 20,
}

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?=((?: ?[A-Z0-9]){11,30}))")
_SSN = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
_SECRET = re.compile(r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/-]{24,}+=*")
_DIGIT = re.compile(r"[0-9]")
_NEAR_WORD = re.compile(r"[^\W\d_]+(?:-[^\W\d_]+)?\d*")


def luhn(digits: str) -> bool:
    """Whether a string of digits passes the mod-10 check."""
    total = 0
    for place, digit in enumerate(reversed(digits)):
        value = ord(digit) - 48
        if place % 2:
            value = value * 2 - 9 if value > 4 else value * 2
        total += value
    return total % 10 == 0


def mod97(account: str) -> bool:
    """Whether an international account number passes the mod-97 check."""
    moved = account[4:] + account[:4]
    rest = 0
    for sign in moved:
        number = int(sign, 36)
        rest = (rest * (100 if number > 9 else 10) + number) % 97
    return rest == 1


def _emails(text: str):
    done = 0
    for match in _DOMAIN.finditer(text):
        # A local part has no "@", so the runs that are walked here are disjoint.
        start = at = match.start()
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        done = max(done, at)
        if start < at:
            done = match.end()
            yield start, done


def _short(part: str) -> bool:
    part = part.lstrip("0")
    return len(part) < 3 or len(part) == 3 and part <= "255"


def _ips(text: str):
    for match in _IP.finditer(text):
        if all(map(_short, match.group().split("."))):
            yield match.span()


def _cards(text: str):
    for match in _CARD.finditer(text):
        if match.end() - match.start() >= 14:
            digits = match.group().replace(" ", "").replace("-", "")
            if 14 <= len(digits) <= 19 and luhn(digits):
                yield match.span()


def _phones(text: str):
    for match in _PHONE.finditer(text):
        if 10 <= len(_DIGIT.findall(match.group())) <= 15:
            yield match.span()


def _iban_end(text: str, start: int, end: int) -> int | None:
    """Where the account number that begins at ``start`` ends, at ``end`` at the latest.

    Its country says how long it is. Of an unknown country the longest run of
    whole groups that passes the check is taken, as what follows may be a word
    in capitals.
    """
    wanted = IBAN_LENGTHS.get(text[start : start + 2])
    signs = [at for at in range(start, end) if text[at] != " "]
    for count in [wanted] if wanted else range(min(34, len(signs)), 14, -1):
        if count <= len(signs):
            after = signs[count - 1] + 1
            ended = after == len(text) or not text[after].isalnum() or not text[after].isascii()
            if ended and mod97(text[start:after].replace(" ", "")):
                return after
    return None


def _ibans(text: str):
    done = 0
    for match in _IBAN.finditer(text):
        if match.start() >= done and (end := _iban_end(text, match.start(), match.end(1))):
            done = end
            yield match.start(), end


def _ssns(text: str):
    for match in _SSN.finditer(text):
        area, group, serial = match.group().split("-")
        if area not in ("000", "666") and area < "900" and group != "00" and serial != "0000":
            yield match.span()


def _secrets(text: str):
    for match in _SECRET.finditer(text):
        value = match.group()
        if _DIGIT.search(value) and len(set(value)) >= 10:
            yield match.span()


_FINDERS = (_emails, _ips, _cards, _phones, _ibans, _ssns, _secrets)


def _score(text: str, kind: str, start: int, end: int, reach: int) -> float:
    near = f"{text[max(0, start - reach):start]} {text[end:end + reach]}".lower()
    words = set(_NEAR_WORD.findall(near))
    score = PRIOR[kind] + 0.25 * bool(words & FOR_KIND[kind]) - 0.25 * bool(words & AGAINST_KIND[kind])
    return min(1.0, max(0.0, score))


def spans_in(text: str | None, reach: int = 40, threshold: float = 0.6) -> list[tuple[str, int, int, float]]:
    """Spans ``(kind, start, end, score)`` by start, then by the order of KINDS; none for null."""
    if not text:
        return []
    digits = _DIGIT.search(text) is not None
    found = []
    for order, (kind, finder) in enumerate(zip(KINDS, _FINDERS, strict=True)):
        if not (digits or kind == "email"):
            continue
        for start, end in finder(text):
            score = _score(text, kind, start, end, reach)
            if order < len(BASE_KINDS) or score >= threshold:
                found.append((start, order, kind, end, score))
    found.sort()
    return [(kind, start, end, score) for start, _, kind, end, score in found]


def private_spans(text: str | Column, reach: int = 40, threshold: float = 0.6) -> Column:
    """A column of the spans in ``text``: ``array<struct<kind, start, end, score>>``.

    Offsets count code points and ``end`` is exclusive. A null or empty text
    has an empty array. Spans of different kinds may overlap.
    """

    @F.arrow_udf(T.ArrayType(SPAN))
    def find(texts: pa.Array) -> pa.Array:
        rows = [
            [dict(zip(("kind", "start", "end", "score"), span, strict=True)) for span in spans_in(text, reach, threshold)]
            for text in values(texts)
        ]
        return pa.array(rows, _ARROW_SPANS)

    return find(F.col(text) if isinstance(text, str) else text)


def redact(documents: DataFrame, text: str = "text", into: str = "redacted", **options) -> DataFrame:
    """Adds ``into``, where each span is replaced by its kind in angle brackets.

    Of overlapping spans the first wins. Null stays null. A column ``into``
    that exists already is replaced.
    """

    @F.arrow_udf(T.StringType())
    def mask(texts: pa.Array) -> pa.Array:
        out = []
        for value in values(texts):
            parts, done = [], 0
            for kind, start, end, _ in spans_in(value, **options):
                if start >= done:
                    parts += [value[done:start], f"<{kind}>"]
                    done = end
            out.append(value if not parts else "".join(parts) + value[done:])
        return pa.array(out, pa.string())

    return documents.withColumn(into, mask(F.col(text)))


def detect(documents: DataFrame, id_column: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """One row per document: its id and ``spans``. Repeated ids give repeated rows; an empty table gives none."""
    return documents.select(F.col(id_column), private_spans(text, **options).alias("spans"))


def span_digest(found: DataFrame) -> DataFrame:
    """Counts of base spans, the SHA-256 of the base spans' list, and the list of all spans."""
    kind = lambda name: F.size(F.filter("spans", lambda s: s.kind == name)).cast("long")
    listed = lambda spans: F.array_join(
        F.transform(spans, lambda s: F.concat_ws(":", s.kind, s.start, s.end)), ","
    )
    base = F.filter("spans", lambda s: s.kind.isin(*BASE_KINDS))
    return found.select(
        "doc_id",
        *(kind(name).alias(f"n_{name}") for name in BASE_KINDS),
        F.sha2(listed(base), 256).alias("base_sha256"),
        listed(F.col("spans")).alias("spans"),
        F.coalesce(F.array_max(F.transform("spans", lambda s: s.score)), F.lit(0.0)).alias("top_score"),
    )
