"""Format-preserving pseudonyms for personal data.

Numbers and dates that validate (card numbers by the Luhn sum, IBANs modulo 97, IPv4 octets, telephone numbers by length, social
security numbers by their excluded ranges, calendar dates), the local parts of e-mail addresses and secrets behind a keyword are
replaced within their own format: a keyed Feistel network permutes the set of all values of that format, so that

* equal values get equal pseudonyms in all documents, and different values different ones;
* a pseudonym has the same length, punctuation and letter case, and validates again (check digits are made anew).

No state is shared: every row is worked on by itself. Defined results: null stays null, empty texts and texts without such data
stay as they are; other columns pass through untouched. The key is a parameter.
"""

from __future__ import annotations

import datetime
import re
from collections.abc import Callable, Iterator
from hashlib import blake2b
from math import isqrt

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

KEY = b"pseudonym key of the production query"
ROUNDS = 8
SCHEMA = "doc_id long, text string, n_replaced int, kinds string"
KINDS = ("email", "secret", "iban", "ip", "ssn", "date", "phone", "card")

# fixed values: the formats looked for
PATTERN = re.compile(
    r"""(?P<email>(?<![A-Za-z0-9._%+\-])[A-Za-z0-9._%+\-]{1,64}@[A-Za-z0-9\-]{1,63}(?:\.[A-Za-z0-9\-]{1,63}){0,8}\.[A-Za-z]{2,24}(?![A-Za-z0-9]))
  |(?<![A-Za-z0-9])(?i:token|secret|passw(?:or)?d|api[_\-]?key|access[_\-]?key)["']?[ ]?[=:][ ]?["']?(?P<secret>(?=[A-Za-z_+/\-]*[0-9])[A-Za-z0-9_+/\-]{16,512})
  |(?<![A-Za-z0-9])(?P<iban>[A-Z]{2}[0-9]{2}(?:[ ]?[A-Z0-9]{4}){2,7}(?:[ ]?[A-Z0-9]{1,3})?)(?![A-Za-z0-9])
  |(?<![0-9.])(?P<ip>[0-9]{1,3}(?:\.[0-9]{1,3}){3})(?!\.?[0-9])
  |(?<![0-9\-])(?P<ssn>[0-9]{3}-[0-9]{2}-[0-9]{4})(?!-?[0-9])
  |(?<![0-9./\-])(?P<date>[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{1,2}[./][0-9]{1,2}[./][0-9]{4})(?![0-9]|[./\-][0-9])
  |(?<![A-Za-z0-9+])(?P<phone>\+1[ .\-]?\(?[0-9]{3}\)?[ .\-]?[0-9]{3}[ .\-]?[0-9]{4}|\+(?!1[ .\-(])[0-9]{1,3}[ \-]?(?:\([0-9]{1,4}\)[ \-]?)?[0-9]{2,4}(?:[ \-]?[0-9]{2,4}){1,4}|\([2-9][0-9]{2}\)[ ]?[0-9]{3}[\-. ][0-9]{4}|(?<!-)[2-9][0-9]{2}[\-.][0-9]{3}[\-.][0-9]{4})(?![0-9]|-[0-9])
  |(?<![0-9])(?P<card>[0-9](?:[ \-]?[0-9]){12,18})(?![0-9])""",
    re.VERBOSE,
)
HINT = re.compile(r"[0-9]")


class Pseudonyms:
    """Keyed permutations of {0..size-1}, and of the formats above."""

    def __init__(self, key: bytes = KEY):
        self.key = blake2b(key, digest_size=32).digest()
        self.memory: dict[tuple[str, str], str | None] = {}

    def permute(self, value: int, size: int, tweak: str) -> int:
        """A Feistel network over pairs (value // side, value % side); values outside of the set are permuted again until they are inside."""
        if size < 2:
            return value
        side = isqrt(size - 1) + 1
        width = (side.bit_length() + 7) // 8
        while True:
            left, right = divmod(value, side)
            for turn in range(ROUNDS):
                mixed = blake2b(right.to_bytes(width, "big"), key=self.key, salt=turn.to_bytes(16, "big"), person=blake2b(f"{tweak}|{size}".encode(), digest_size=16).digest(), digest_size=min(64, width + 8)).digest()
                left, right = right, (left + int.from_bytes(mixed, "big")) % side
            value = left * side + right
            if value < size:
                return value

    def characters(self, text: str, tweak: str) -> str:
        """Digits become digits and letters letters of the same case; anything else stays in its place."""
        sets = ["0123456789" if c in "0123456789" else "abcdefghijklmnopqrstuvwxyz" if "a" <= c <= "z" else "ABCDEFGHIJKLMNOPQRSTUVWXYZ" if "A" <= c <= "Z" else c for c in text]
        value, size = 0, 1
        for c, chars in zip(text, sets, strict=True):
            value, size = value * len(chars) + chars.index(c), size * len(chars)
        shape = "".join(chars[0] if len(chars) > 1 else c for c, chars in zip(text, sets, strict=True))
        value, out = self.permute(value, size, f"{tweak}|{shape}"), []
        for chars in reversed(sets):
            value, at = divmod(value, len(chars))
            out.append(chars[at])
        return "".join(reversed(out))

    def hexadecimal(self, text: str, tweak: str) -> str:
        value = self.permute(int(text, 16), 16 ** len(text), tweak)
        new = f"{value:0{len(text)}x}"
        return new.upper() if text.upper() == text else new

    def email(self, text: str) -> str:
        local, _, domain = text.partition("@")
        return f"{self.characters(local, 'email|' + domain.lower())}@{domain}"

    def secret(self, text: str) -> str | None:
        if re.fullmatch("[0-9a-f]+|[0-9A-F]+", text):
            return self.hexadecimal(text, "secret")
        return self.characters(text, "secret")

    def iban(self, text: str) -> str | None:
        plain = text.replace(" ", "")
        if not 15 <= len(plain) <= 34 or _iban_value(plain) % 97 != 1:
            return None
        body = self.characters(plain[4:], "iban|" + plain[:2])
        check = 98 - _iban_value(plain[:2] + "00" + body) % 97
        return _fill(text, f"{plain[:2]}{check:02d}{body}", lambda c: c != " ")

    def ip(self, text: str) -> str | None:
        parts = [int(x) for x in text.split(".")]
        if max(parts) > 255 or any(len(x) > 1 and x[0] == "0" for x in text.split(".")):
            return None
        value = self.permute(int.from_bytes(bytes(parts), "big"), 1 << 32, "ip")
        return ".".join(map(str, value.to_bytes(4, "big")))

    def ssn(self, text: str) -> str | None:
        area, group, serial = map(int, text.split("-"))
        if area in (0, 666) or area >= 900 or not group or not serial:
            return None
        rank = ((area - 1 - (area > 666)) * 99 + group - 1) * 9999 + serial - 1
        area, rest = divmod(self.permute(rank, 898 * 99 * 9999, "ssn"), 99 * 9999)
        return f"{area + 1 + (area >= 665):03d}-{rest // 9999 + 1:02d}-{rest % 9999 + 1:04d}"

    def date(self, text: str) -> str | None:
        """Within the same century, so that pseudonyms stay plausible; the order of day and month is kept."""
        numbers = [int(x) for x in re.split("[-./]", text)]
        marks = re.findall("[-./]", text)
        if marks[0] != marks[1]:
            return None
        iso = marks[0] == "-"
        year, month, day = numbers if iso else (numbers[2], numbers[1], numbers[0])
        swapped = not iso and month > 12
        if swapped:
            month, day = day, month
        try:
            when = datetime.date(year, month, day)
            first, last = datetime.date(max(1, year // 100 * 100), 1, 1), datetime.date(year // 100 * 100 + 99, 12, 31)
        except ValueError:
            return None
        # a form without leading zeros, and one in which only one order of day and month is possible, are sets of their own
        days = [first + datetime.timedelta(d) for d in range((last - first).days + 1)]
        form = lambda d: (d.year, d.month, d.day) if iso else (d.day, d.month, d.year) if not swapped else (d.month, d.day, d.year)
        widths = [len(x) for x in re.split("[-./]", text)]
        fits = [d for d in days if all(len(str(x)) <= w and (w == 4 or w == 2 or len(str(x)) == w) for x, w in zip(form(d), widths, strict=True)) and (not swapped or d.day > 12)]
        new = fits[self.permute(fits.index(when), len(fits), f"date|{iso}|{swapped}|{widths}|{year // 100}|{marks[0]}")]
        return marks[0].join(f"{x:0{w}d}" for x, w in zip(form(new), widths, strict=True))

    def phone(self, text: str) -> str | None:
        digits = re.sub("[^0-9]", "", text)
        if not 8 <= len(digits) <= 15:
            return None
        code = len(re.match(r"\+?([0-9]*)", text)[1]) if text[0] == "+" and re.match(r"\+[0-9]{1,3}[ .\-(]", text) else 1 if text[0] == "+" else 0
        return _fill(text, digits[:code] + self.characters(digits[code:], "phone|" + digits[:code]), str.isdigit)

    def card(self, text: str) -> str | None:
        digits = re.sub("[^0-9]", "", text)
        if not 13 <= len(digits) <= 19 or _luhn(digits) or len(set(digits)) == 1:
            return None
        body = digits[0] + self.characters(digits[1:-1], "card|" + digits[0])
        return _fill(text, body + str(-_luhn(body + "0") % 10), str.isdigit)

    def pseudonym(self, kind: str, text: str) -> str | None:
        """The pseudonym, or None where the value isn't valid."""
        found = self.memory.get((kind, text), "")
        if found == "":
            if len(self.memory) > 100_000:
                self.memory.clear()
            found = self.memory[kind, text] = getattr(self, kind)(text)
        return found

    def apply(self, text: str | None) -> tuple[str | None, dict[str, int]]:
        """The text with pseudonyms, and how many of each kind."""
        counts: dict[str, int] = {}
        if not text or not ("@" in text or HINT.search(text)):
            return text, counts

        out, done, pos = [], 0, 0
        while match := PATTERN.search(text, pos):
            kind, new = match.lastgroup, None
            found = match[kind]
            # a number may have run into its neighbour: shorter forms of it are tried too
            for found in [found, *(found[: m.start()] for m in reversed([*re.finditer("[ -]", found)]) if kind in ("card", "phone"))]:
                if (kind != "card" or len(found) >= 13) and (new := self.pseudonym(kind, found)) is not None:
                    break
            if new is None:
                pos = match.start() + 1
                continue
            counts[kind] = counts.get(kind, 0) + 1
            out += (text[done : match.start(kind)], new)
            done = pos = match.start(kind) + len(found)
        return "".join((*out, text[done:])), counts


def _luhn(digits: str) -> int:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10


def _iban_value(plain: str) -> int:
    return int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4]))


def _fill(shape: str, new: str, slot: Callable[[str], bool]) -> str:
    given = iter(new)
    return "".join(next(given) if slot(c) else c for c in shape)


def pseudonymise(documents: DataFrame, text_column: str = "text", key: bytes = KEY) -> DataFrame:
    """The same rows and columns, with pseudonyms in the text column."""
    at = documents.columns.index(text_column)

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = Pseudonyms(key)
        for batch in slices(batches):
            column = batch.column(at)
            texts = column.cast(pa.string()).to_pylist()
            yield batch.set_column(at, batch.schema.field(at), pa.array([names.apply(t)[0] for t in texts], pa.string()).cast(column.type))

    return documents.mapInArrow(apply, documents.schema)


def report(documents: DataFrame, key: bytes = KEY) -> DataFrame:
    """doc_id, text with pseudonyms, n_replaced and kinds (`kind:count`, comma-separated, null if none)."""

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = Pseudonyms(key)
        for batch in slices(batches):
            done = [names.apply(t.as_py()) for t in batch.column(1)]
            said = [",".join(f"{k}:{c[k]}" for k in KINDS if k in c) or None for _, c in done]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([t for t, _ in done], pa.string()), pa.array([sum(c.values()) for _, c in done], pa.int32()), pa.array(said, pa.string())], names=["doc_id", "text", "n_replaced", "kinds"])

    return documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(apply, SCHEMA)
