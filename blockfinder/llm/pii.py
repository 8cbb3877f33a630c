"""Personal data: format-preserving pseudonyms by keyed Feistel permutations.

Numbers, dates, addresses and secrets that pass their own validation are replaced by others of the same format and
validity. The permutation depends on the key, the kind and the format alone, so equal values get equal pseudonyms in
all documents, and whoever holds the key can reverse them. What fails its validation (a card number with a wrong check
digit, the 31st of June) is left alone.
"""

from __future__ import annotations

import datetime
import hashlib
import re
import warnings
from collections.abc import Callable

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

from .common import arrow_map, documents, making_room

#: For tests and trials; give a secret key of your own in production.
TRIAL_KEY = b"trial key, not for production"
KEY_SETTING = "spark.blockfinder.pseudonymKey"  # of the session: the key that jobs use
ROUNDS = 10
DIGITS, LETTERS, HEX = "0123456789", "abcdefghijklmnopqrstuvwxyz", "0123456789abcdef"
FIRST_DAY, DAYS = datetime.date(1900, 1, 1).toordinal(), datetime.date(2099, 12, 31).toordinal() - datetime.date(1900, 1, 1).toordinal() + 1


def permute(values: list[int], sizes: list[int], key: bytes, tweak: str, inverse: bool = False) -> list[int]:
    """A keyed permutation of the vectors with ``0 <= values[i] < sizes[i]``.

    The vector is split into two numbers of mixed base; each round adds a keyed hash of one to the other, in its range.
    """
    cut = len(sizes) // 2
    halves, bounds = [0, 0], [1, 1]
    for k, (v, n) in enumerate(zip(values, sizes, strict=True)):
        side = k >= cut
        halves[side], bounds[side] = halves[side] * n + v, bounds[side] * n
    seed = hashlib.blake2b(tweak.encode(), key=key[:64], digest_size=32).digest()
    for r in reversed(range(ROUNDS)) if inverse else range(ROUNDS):
        side = r % 2
        other = halves[1 - side]
        width = max(32, -(-bounds[side].bit_length() // 8) + 16)
        step, block = b"", 0
        while len(step) < width:
            step += hashlib.blake2b(bytes([r, block]) + other.to_bytes(-(-bounds[1 - side].bit_length() // 8) + 1, "big"), key=seed, digest_size=64).digest()
            block += 1
        moved = int.from_bytes(step[:width], "big")
        halves[side] = (halves[side] + (-moved if inverse else moved)) % bounds[side]
    out = []
    for side, own in ((1, sizes[cut:]), (0, sizes[:cut])):
        rest = halves[side]
        for n in reversed(own):
            rest, v = divmod(rest, n)
            out.append(v)
    return out[::-1]


def permute_text(text: str, key: bytes, tweak: str, alphabets: tuple[str, ...], inverse: bool = False, valid: Callable[[str], bool] = lambda s: True) -> str:
    """Permute the characters of ``text`` that are in one of the alphabets within it; the rest, and case, stay.

    Where the pseudonym must be valid, the permutation is repeated until it is; that is a permutation of valid values.
    """
    low = text.lower()
    own = [next((a for a in alphabets if c in a), None) for c in low]
    at = [k for k, a in enumerate(own) if a]
    shape = "".join("." if a is None else chr(65 + alphabets.index(a)) for a in own) + "".join(c for c, a in zip(low, own, strict=True) if a is None)
    values, sizes = [own[k].index(low[k]) for k in at], [len(own[k]) for k in at]
    if not at:
        return text
    capitals = text.isupper()
    while True:
        values = permute(values, sizes, key, f"{tweak}|{shape}", inverse)
        out = list(text)
        for k, v in zip(at, values, strict=True):
            out[k] = own[k][v].upper() if text[k].isupper() or capitals else own[k][v]
        if valid("".join(out)):
            return "".join(out)


def luhn_digit(digits: str) -> int:
    """The check digit that belongs behind ``digits``."""
    total = sum(int(d) if k % 2 else sum(divmod(2 * int(d), 10)) for k, d in enumerate(reversed(digits)))
    return -total % 10


def only_digits(text: str) -> str:
    return "".join(c for c in text if c in DIGITS)


def refill(text: str, digits: str) -> str:
    """``text`` with its digits replaced, one by one."""
    take = iter(digits)
    return "".join(next(take) if c in DIGITS else c for c in text)


def card(text: str, key: bytes, inverse: bool) -> str | None:
    digits = only_digits(text)
    if not 13 <= len(digits) <= 19 or luhn_digit(digits[:-1]) != int(digits[-1]) or len(set(digits)) == 1:
        return None
    body = permute_text(digits[:-1], key, "card", (DIGITS,), inverse, lambda s: len(set(s)) > 1)
    return refill(text, f"{body}{luhn_digit(body)}")


def iban_digits(country: str, body: str) -> str:
    number = int("".join(str(int(c, 36)) for c in f"{body}{country}00"))
    return f"{98 - number % 97:02d}"


def iban(text: str, key: bytes, inverse: bool) -> str | None:
    packed = text.replace(" ", "")
    if not 15 <= len(packed) <= 34 or iban_digits(packed[:2], packed[4:]) != packed[2:4]:
        return None
    body = permute_text(packed[4:], key, f"iban{packed[:2]}", (DIGITS, LETTERS), inverse)
    take = iter(packed[:2] + iban_digits(packed[:2], body) + body)
    return "".join(c if c == " " else next(take) for c in text)


def address(text: str, key: bytes, inverse: bool) -> str | None:
    parts = text.split(".")
    if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
        return None
    return ".".join(map(str, permute([int(p) for p in parts], [256] * 4, key, "address", inverse)))


def date(text: str, key: bytes, inverse: bool) -> str | None:
    """Year, month and day in one of the usual orders; where day and month are both possible, the day leads."""
    mark = next(c for c in text if c not in DIGITS)
    parts = text.split(mark)
    orders = (("y", "m", "d"),) if len(parts[0]) == 4 else (("d", "m", "y"), ("m", "d", "y"))
    for order in orders:
        named = dict(zip(order, map(int, parts), strict=True))
        try:
            day = datetime.date(named["y"], named["m"], named["d"]).toordinal() - FIRST_DAY
        except ValueError:
            continue
        if 0 <= day < DAYS:
            # An order that reads two ways must come out as one that reads the same way.
            while True:
                day = permute([day // 277, day % 277], [-(-DAYS // 277), 277], key, f"date{''.join(order)}", inverse)
                day = day[0] * 277 + day[1]
                if day < DAYS:
                    moved = datetime.date.fromordinal(FIRST_DAY + day)
                    if order != ("m", "d", "y") or moved.day > 12:
                        break
            new = {"y": f"{moved.year:04d}", "m": f"{moved.month:02d}", "d": f"{moved.day:02d}"}
            short = any(len(p) == 1 for p in parts)
            return mark.join(new[o].lstrip("0") if short and o != "y" else new[o] for o in order)
    return None


def social(text: str, key: bytes, inverse: bool) -> str | None:
    def valid(s: str) -> bool:
        area, group, serial = s.split("-")
        return area not in ("000", "666") and area[0] != "9" and group != "00" and serial != "0000"

    return permute_text(text, key, "social", (DIGITS,), inverse, valid) if valid(text) else None


#: Country codes by their first digits: one digit, two, or else three.
COUNTRY = re.compile(r"\+(?:[17]|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|\d{3})")


def phone(text: str, key: bytes, inverse: bool) -> str | None:
    """The country code stays."""
    if not 7 <= len(only_digits(text)) <= 15:
        return None
    lead = re.match(r"\+\d{1,3}(?=\D)", text) or COUNTRY.match(text)
    cut = lead.end() if lead else 0
    return text[:cut] + permute_text(text[cut:], key, f"phone{text[:cut]}", (DIGITS,), inverse)


def email(text: str, key: bytes, inverse: bool) -> str | None:
    """The local part is permuted, letters as letters and digits as digits; the domain stays."""
    local, at, domain = text.rpartition("@")
    return permute_text(local, key, f"email{domain.lower()}", (DIGITS, LETTERS), inverse) + at + domain


def secret(text: str, key: bytes, inverse: bool) -> str | None:
    if len(set(text)) < 5 or not any(c in DIGITS for c in text):
        return None
    one_case = text in (text.lower(), text.upper())
    return permute_text(text, key, "secret", (HEX,) if one_case and set(text.lower()) <= set(HEX) else (DIGITS, LETTERS), inverse)


# How each kind is written; earlier kinds win where two begin at one place.
PATTERNS: dict[str, tuple[str, Callable]] = {
    "email": (r"(?<![\w.+-])[A-Za-z0-9][A-Za-z0-9._%+-]{0,63}@(?:[A-Za-z0-9-]{1,63}\.){1,8}[A-Za-z]{2,24}\b", email),
    "secret": (r"(?:(?<=[=:] [\"'])|(?<=[=:][\"'])|(?<=token [=:] )|(?<=secret [=:] )|(?<=key [=:] ))[A-Za-z0-9_+/-]{16,512}(?![A-Za-z0-9_+/-])", secret),
    "iban": (r"(?<!\w)[A-Z]{2}\d\d(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?!\w)", iban),
    "address": (r"(?<![\w.])\d{1,3}\.\d{1,3}\.\d{1,3}\.\d{1,3}(?!\w|\.\d)", address),
    "date": (r"(?<![\w.-])(?:\d{4}([-/.])\d{1,2}\1\d{1,2}|\d{1,2}([-/.])\d{1,2}\2\d{4})(?![\w-]|\.\d)", date),
    "social": (r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])", social),
    "card": (r"(?<![\w.-])\d(?:[ -]?\d){12,18}(?![\w-])", card),
    "phone": (r"(?<![\w.])(?:\+\d{8,15}(?!\w)|(?:\+\d{1,3}[ .-]?)?(?:\(\d{2,4}\)[ .-]?\d{3,4}[ .-]\d{3,4}|(?<=[\d .-])\d{2,4}(?:[ .-]\d{2,4}){2,4}|\d{3}[.-]\d{3}[.-]\d{4}))(?!\w)", phone),
}
KINDS = list(PATTERNS)


def one_pattern() -> re.Pattern:
    """All kinds in one pattern; a kind's own back references are renumbered."""
    parts, groups = [], 0
    for kind, (form, _) in PATTERNS.items():
        groups += 1
        parts.append(f"(?P<{kind}>{re.sub(r'\\([1-9])', lambda m, g=groups: f'\\{int(m[1]) + g}', form)})")
        groups += re.compile(form).groups
    return re.compile("|".join(parts))


ANY = one_pattern()
ALONE = {kind: re.compile(form) for kind, (form, _) in PATTERNS.items()}
#: Kinds that can end in more than one place, with what must hold behind their end.
ENDS = {kind: re.compile(PATTERNS[kind][0][PATTERNS[kind][0].rindex("(?!") :]) for kind in ("iban", "card", "phone")}
ONLY = ("address", "date")  # what is written like these and is not valid is no other kind either
HINT = re.compile("[0-9@]")


class Pseudonyms:
    """Replaces what is found in a text; values seen before are kept, a bounded number of them."""

    def __init__(self, key: bytes, inverse: bool = False, most: int = 100_000):
        self.key, self.inverse, self.known, self.most = key, inverse, {}, most

    def of(self, kind: str, value: str) -> str | None:
        if (kind, value) not in self.known:
            if len(self.known) >= self.most:
                self.known.clear()
            self.known[kind, value] = PATTERNS[kind][1](value, self.key, self.inverse)
        return self.known[kind, value]

    def at(self, text: str, start: int) -> tuple[str, int, str] | None:
        """The first kind that is valid at ``start``, with its end and pseudonym; of its matches, the longest valid one."""
        for kind, pattern in ALONE.items():
            m = pattern.match(text, start)
            if not m:
                continue
            if (new := self.of(kind, m.group())) is not None:
                return kind, m.end(), new
            for end in range(m.end() - 1, start, -1) if kind in ENDS else ():
                if ENDS[kind].match(text, end) and pattern.fullmatch(text, start, end) and (new := self.of(kind, text[start:end])) is not None:
                    return kind, end, new
            if kind in ONLY:
                return None
        return None

    def replace(self, text: str) -> tuple[str, list[tuple[str, int, int]]]:
        """The new text and, in characters of the old one, what was replaced."""
        if not HINT.search(text):
            return text, []
        parts, spans, done, at = [], [], 0, 0
        while m := ANY.search(text, at):
            start = m.start()
            new = self.of(m.lastgroup, m.group()) if m.lastgroup else None
            kind, end, new = (m.lastgroup, m.end(), new) if new is not None else self.at(text, start) or (None, start, None)
            if new is None:  # nothing valid begins here
                at = start + 1
                continue
            parts += [text[done:start], new]
            spans.append((kind, start, end))
            done = at = end
        return "".join(parts) + text[done:], spans


SPANS = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))


def pseudonymise(df: DataFrame, key: bytes = TRIAL_KEY, text: str = "text", inverse: bool = False, prefix: str = "pii_") -> DataFrame:
    """All rows and columns of ``df`` with personal data in its text replaced.

    Adds the number of values replaced and their spans in the old text (kind, start, end, in characters). Null stays
    null and has none. ``inverse`` gives the old text back from a new one.
    """
    df = making_room(df, [f"{prefix}values", f"{prefix}spans"])
    at = df.columns.index(text)
    names = [*df.columns, f"{prefix}values", f"{prefix}spans"]

    def rows(batches):
        pseudonyms = Pseudonyms(key, inverse)
        for batch in batches:
            found = [(None, []) if t is None else pseudonyms.replace(t) for t in batch.column(at).to_pylist()]
            columns = batch.columns
            columns[at] = pa.array([t for t, _ in found], batch.column(at).type)
            spans = pa.array([[dict(zip(("kind", "start", "end"), s, strict=True)) for s in x] for _, x in found], SPANS)
            yield pa.RecordBatch.from_arrays([*columns, pc.list_value_length(spans).cast(pa.int64()), spans], names)

    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields]
    return arrow_map(df, rows, ", ".join([*fields, f"`{prefix}values` long", f"`{prefix}spans` array<struct<kind:string,start:long,end:long>>"]))


def session_key(spark: SparkSession) -> bytes:
    """The session's ``spark.blockfinder.pseudonymKey``. Where it is unset, the trial key, which anybody can undo, with a warning."""
    key = spark.conf.get(KEY_SETTING, None)
    if key:
        return key.encode()
    warnings.warn(f"{KEY_SETTING} is not set: pseudonyms are made with a public trial key", stacklevel=2)
    return TRIAL_KEY


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pseudonymise(documents(spark, sf_dir).select("doc_id", "text"), session_key(spark))


def without_personal_data(docs: DataFrame, key: bytes | None = None) -> DataFrame:
    """The rows of ``docs``, with its columns and new texts; the key is the session's unless one is given."""
    return pseudonymise(docs, key or session_key(docs.sparkSession), prefix="__p_").select(*docs.columns)
