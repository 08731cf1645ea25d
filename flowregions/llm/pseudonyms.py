"""Pseudonyms for personal data that keep the format, by a keyed Feistel network.

Values are found, validated and permuted within their own format, so the same value becomes the same
pseudonym in every document and a valid value stays a valid one:

- payment cards: 13 to 19 digits with a right Luhn sum; all digits but the last are permuted, the
  last is the Luhn digit of the new number;
- IBANs with a right remainder: the account part is permuted, the check digits are computed anew;
- dates (year-month-day, day.month.year, month/day/year) that exist: permuted among the days of 400 years
  that can be written in as many digits;
- telephone numbers: all digits behind the country code; IPv4 addresses: all four bytes;
- social security numbers: within the valid ranges;
- e-mail addresses: letters and digits of the part before the @ and of the domain but for its last label; passwords, tokens, keys and other
  secrets behind a name: letters and digits of the value; keys of known forms (AKIA..., ghp_...): what follows their mark.

The permutation is a Feistel network of ten rounds over mixed radix (any alphabets at any place);
round values are keyed BLAKE2b. Where a format forbids some values, the network is walked until the
value is allowed again, which keeps it a permutation of the allowed values: different values never share
a pseudonym. A permutation may leave a value where it is; among values of few digits that can happen.
"""

from __future__ import annotations

import datetime
import hashlib
import re
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame

from flowregions.llm.common import give_back, text_batches

ROUNDS = 10
DIGITS, LOWER, UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
HEX = "0123456789abcdef"

#: Kinds of values and how they look; the groups "s" mark what is replaced.
PATTERNS = (
    ("email", r"(?<![A-Za-z0-9._%+-])[._%+-]*+(?P<email>[A-Za-z0-9][A-Za-z0-9._%+-]*+@(?:[A-Za-z0-9-]++\.)+[A-Za-z]{2,})"),
    ("secret", r"(?P<secret>(?i:\b(?:pass(?:word|wd)?|pwd|secret|token|api[_-]?key|access[_-]?key|auth)\b[\"']?\s*[=:]\s*[\"']?))(?P<secret_value>[A-Za-z0-9_+/.-]{6,}=*)"),
    ("token", r"(?P<token>\b(?:(?:AKIA|ASIA)[A-Z0-9]{16}|gh[pousr]_[A-Za-z0-9]{20,}|sk-[A-Za-z0-9_-]{20,}|xox[abprs]-[A-Za-z0-9-]{10,})\b)"),
    ("date", r"(?P<date>(?<![\d.])(?:\d{4}-\d{2}-\d{2}|\d{1,2}\.\d{1,2}\.\d{4}|\d{1,2}/\d{1,2}/\d{4})(?![\d]|\.\d))"),
    ("ip", r"(?P<ip>(?<![\d.])\d{1,3}\.\d{1,3}\.\d{1,3}\.\d{1,3}(?!\d|\.\d))"),
    ("iban", r"(?P<iban>\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b)"),
    ("ssn", r"(?P<ssn>(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-]))"),
    ("phone", r"(?P<phone>(?:\+\d{1,3}[ .-]?)?\(\d{2,4}\)[ .-]?\d{3,4}[ .-]?\d{3,4}(?!\d)|\+\d{1,3}(?:[ .-]?\d{2,4}){2,5}(?!\d)|(?<![\d.+-])\d{3}[ .-]\d{3,4}[ .-]\d{4}(?![\d-]))"),
    ("card", r"(?P<card>(?<![\d-])(?<!\d\.)\d(?:[ -]?\d){12,18}(?![\d-]|\.\d))"),
)
CARD = re.compile(PATTERNS[-1][1])
FINDER = re.compile("|".join(p for _, p in PATTERNS))
#: A text without any of these holds none of the kinds.
HINT = re.compile(r"[0-9@]|AKIA|ASIA|(?i:pass|pwd|secret|token|key|auth)")


def permute(value: list[int], radix: list[int], key: bytes, tweak: str) -> list[int]:
    """A keyed permutation of the numbers with these places: two halves take turns to shift each other."""
    if len(value) == 1:
        # one place has no halves: keyed shuffle of its symbols
        order = sorted(range(radix[0]), key=lambda s: hashlib.blake2b(f"{tweak}:{radix[0]}:{s}".encode(), key=key, digest_size=8).digest())
        return [order[value[0]]]
    half = len(value) // 2
    sizes = [1, 1]
    for k, r in enumerate(radix):
        sizes[k >= half] *= r
    left = right = 0
    for v, r in zip(value[:half], radix[:half], strict=True):
        left = left * r + v
    for v, r in zip(value[half:], radix[half:], strict=True):
        right = right * r + v
    for k in range(ROUNDS):
        other, size = (right, sizes[0]) if k % 2 == 0 else (left, sizes[1])
        wide = (size.bit_length() + 7) // 8 + 8
        block = hashlib.shake_256(key + f"{tweak}:{len(value)}:{k}:{other}".encode()).digest(wide)
        shift = int.from_bytes(block, "big")
        if k % 2 == 0:
            left = (left + shift) % sizes[0]
        else:
            right = (right + shift) % sizes[1]
    out = []
    for n, part in ((right, radix[half:]), (left, radix[:half])):
        for r in reversed(part):
            out.append(n % r)
            n //= r
    return out[::-1]


def characters(text: str, key: bytes, tweak: str) -> str:
    """Letters and digits permuted each within its own kind (hexadecimal secrets stay so); all else stays in place."""
    hexadecimal = tweak == "secret" and bool(re.fullmatch(r"[0-9a-f]{8,}", text))
    places, alphabets = [], []
    for k, c in enumerate(text):
        for a in (HEX,) if hexadecimal else (DIGITS, LOWER, UPPER):
            if c in a:
                places.append(k)
                alphabets.append(a)
    if not places:
        return text
    form = tweak + "".join("x" if a is HEX else a[0] for a in alphabets)
    value, radix = [a.index(text[k]) for k, a in zip(places, alphabets, strict=True)], [len(a) for a in alphabets]
    new = permute(value, radix, key, form)
    out = list(text)
    for k, a, v in zip(places, alphabets, new, strict=True):
        out[k] = a[v]
    return "".join(out)


def luhn(digits: str) -> int:
    """The digit that makes the Luhn sum of digits + it divisible by 10."""
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (2 - k % 2)
        total += d - 9 if d > 9 else d
    return -total % 10


def _refill(shape: str, digits: str) -> str:
    left = iter(digits)
    return "".join(next(left) if c.isalnum() else c for c in shape)


def card(text: str, key: bytes) -> str | None:
    digits = re.sub(r"\D", "", text)
    if luhn(digits[:-1]) != int(digits[-1]) or len(set(digits)) == 1:
        return None
    body = characters(digits[:-1], key, "card")
    return _refill(text, body + str(luhn(body)))


def card_within(text: str, key: bytes) -> tuple[str | None, int]:
    """The longest run of whole groups from the start that is a card number, and its length: what follows a number may be another one."""
    for end in [len(text), *(m.start() for m in reversed(list(re.finditer(r"[ -]", text))))]:
        if 13 <= sum(c.isdigit() for c in text[:end]) <= 19 and (new := card(text[:end], key)) is not None:
            return new, end
    return None, 0


def token(text: str, key: bytes) -> str | None:
    """Keys of known forms: what marks the form stays."""
    lead = re.match(r"AKIA|ASIA|gh[pousr]_|sk-|xox[abprs]-", text).end()
    return text[:lead] + characters(text[lead:], key, "token")


def _remainder(text: str) -> int:
    return int("".join(str(int(c, 36)) for c in text)) % 97


def iban(text: str, key: bytes) -> str | None:
    plain = text.replace(" ", "")
    if _remainder(plain[4:] + plain[:4]) != 1:
        return None
    body = characters(plain[4:], key, "iban" + plain[:2])
    return _refill(text, plain[:2] + f"{98 - _remainder(body + plain[:2] + '00'):02d}" + body)


#: Days that dates are permuted among.
FIRST_DAY, LAST_DAY = datetime.date(1700, 1, 1).toordinal(), datetime.date(2099, 12, 31).toordinal()


def date(text: str, key: bytes) -> str | None:
    parts = re.split(r"[-./]", text)
    order = (0, 1, 2) if "-" in text else (2, 1, 0) if "." in text else (2, 0, 1)
    try:
        day = datetime.date(*(int(parts[k]) for k in order)).toordinal()
    except ValueError:
        return None
    if not FIRST_DAY <= day <= LAST_DAY:
        return None
    # a day or month in one digit keeps one; in two digits a zero may stand before
    one = [len(parts[order[k]]) == 1 for k in (1, 2)]
    fits = lambda d: all(value < 10 or not narrow for value, narrow in zip((d.month, d.day), one, strict=True))
    places = [int(c) for c in f"{day - FIRST_DAY:06d}"]
    while True:  # 146,097 of a million values are days: seven steps on average, more for dates in fewer digits
        places = permute(places, [10] * 6, key, "date")
        n = int("".join(map(str, places)))
        if FIRST_DAY + n <= LAST_DAY and fits(new := datetime.date.fromordinal(FIRST_DAY + n)):
            break
    values = {order[0]: f"{new.year:04d}"}
    for k, value, narrow in ((1, new.month, one[0]), (2, new.day, one[1])):
        values[order[k]] = str(value) if narrow else f"{value:02d}"
    mark = next(c for c in text if not c.isdigit())
    return mark.join(values[k] for k in range(3))


def ip(text: str, key: bytes) -> str | None:
    value = [int(p) for p in text.split(".")]
    if max(value) > 255:
        return None
    new = permute(value, [256] * 4, key, "ip")
    return ".".join(map(str, new))


def ssn(text: str, key: bytes) -> str | None:
    valid = lambda t: t[:3] not in ("000", "666") and t[0] != "9" and t[4:6] != "00" and t[7:] != "0000"
    if not valid(text):
        return None
    while True:
        text = characters(text, key, "ssn")
        if valid(text):
            return text


def phone(text: str, key: bytes) -> str | None:
    lead = re.match(r"\+\d{1,3}(?=[ .(-])|\+\d", text)
    at = lead.end() if lead else 0
    if not 7 <= sum(c.isdigit() for c in text) <= 15:
        return None
    return text[:at] + characters(text[at:], key, "phone")


def email(text: str, key: bytes) -> str | None:
    name, _, domain = text.rpartition("@")
    host, _, last = domain.rpartition(".")
    return characters(name, key, "email") + "@" + characters(host, key, "domain") + "." + last


KINDS: dict[str, Callable[[str, bytes], str | None]] = {"email": email, "token": token, "date": date, "ip": ip, "iban": iban, "ssn": ssn, "phone": phone, "card": card}


def pseudonymise(text: str | None, key: bytes) -> tuple[str | None, list[tuple[int, int, str]]]:
    """(the text with pseudonyms, (start, end, kind) of the replaced values in the original)."""
    if not text or not HINT.search(text):
        return text, []
    out, spans, at, pos = [], [], 0, 0
    while m := FINDER.search(text, pos):
        kind = m.lastgroup if m.lastgroup != "secret_value" else "secret"
        if kind == "secret":
            start, stop = m.span("secret_value")
            new = characters(m.group("secret_value"), key, "secret")
        else:
            start, stop = m.span(kind)
            new = KINDS[kind](m.group(kind), key)
            if new is None and kind in ("phone", "card"):  # a number that is no telephone's may still be a card's
                wide = CARD.match(text, start)
                if wide:
                    new, size = card_within(wide.group(), key)
                    stop, kind = start + size, "card"
        if new is None:
            pos = start + 1
            while pos < len(text) and text[pos].isalnum() and text[pos - 1].isalnum():
                pos += 1
            continue
        out += [text[at:start], new]
        spans.append((start, stop, kind))
        at = pos = stop
    return "".join([*out, text[at:]]), spans


def protect(docs: DataFrame, key: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text, n_values, spans) of every row: one pass, no shuffle; the same key gives the same pseudonyms in every run and document.

    Null texts stay null and empty texts empty, both with no spans. Numbers that only look like a kind (wrong
    check digits, impossible dates or addresses) stay. Repeated rows stay repeated, rows without an id are
    served like others. Very long texts are scanned once, in time linear in their length. Where two kinds fit at
    one place, the first in PATTERNS is taken. An empty table gives no rows. No other column is read or returned,
    so names cannot clash.
    """
    import pyarrow as pa

    secret = hashlib.blake2b(key.encode(), digest_size=32).digest()
    text_batches(docs.sparkSession)
    frame = docs.select(docs[id_col].alias("id"), docs[text_col].cast("string").alias("text"))
    kind = frame.schema["id"].dataType.simpleString()
    span = pa.list_(pa.struct([pa.field("start", pa.int32()), pa.field("end", pa.int32()), pa.field("kind", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                done = [pseudonymise(t, secret) for t in part.column(1).to_pylist()]
                spans = [[{"start": a, "end": b, "kind": c} for a, b, c in s] for _, s in done]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([t for t, _ in done], pa.string()), pa.array([len(s) for s in spans], pa.int32()), pa.array(spans, span)], ["id", "text", "n_values", "spans"])
        give_back()

    out = frame.mapInArrow(run, f"id {kind}, text string, n_values int, spans array<struct<start:int,end:int,kind:string>>")
    return out.withColumnRenamed("id", id_col).withColumnRenamed("text", text_col)
