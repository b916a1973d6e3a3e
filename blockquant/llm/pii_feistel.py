"""Personal data as format-preserving pseudonyms.

Values are found by pattern and kept only if they validate (calendar, Luhn, mod 97, number plans, octets). A keyed Feistel
network permutes each value inside the set of values of its own format: a card number becomes another card number with a
right check digit, a date another date in the same layout. The permutation depends on the key and the kind of value, not
on the document, so equal values stay linked everywhere, and the holder of the key can undo it (``reveal=True``).

What is permuted, with what stays:

* payment cards (13-19 digits, Luhn): all but the first digit; the check digit is set anew
* IBANs (mod 97): the letters and digits of the account; country stays, check digits are set anew
* phone numbers (+ and 8-15 digits, or 10 digits of the +1 number plan): all but the country code; what is in the +1 plan
  stays in it and what is not stays outside
* social security numbers (valid areas, groups, serials), IPv4 addresses (first octet 1-223)
* dates 1900-2099, as y-m-d, y/m/d, d.m.y, d/m/y or m/d/y: among the dates whose day could or could not be a month
* e-mail addresses: letters and digits of the local part, each in its own kind; the domain stays
* secrets after password, token, secret or key and = or : : letters and digits, each in its own kind, hexadecimal as such,
  of any length

Two networks. Values that are a number in a range (cards, dates, addresses, short words) are permuted as numbers, with
halves of the range's square root; longer ones character by character, the characters of one half moved by a keyed stream
drawn from the other half, which costs time in proportion to the length. In both every round reaches the whole of its half.

Defined results: null stays null, empty stays empty; numbers that don't validate stay as they are; texts are searched whole;
repeated rows give equal results; ``n_pii`` counts replaced values; clashing columns of the input are replaced.
"""

from __future__ import annotations

import datetime
import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from . import common

ROUNDS = 8
#: Characters up to which a value is permuted as one number: no half is then wider than the keyed hash.
AS_NUMBER = 64
ANCHOR = re.compile(r"[0-9@=:]")  # every match of FOUND has one among its first 80 characters
SPACE = re.compile(r"\s")
FOUND = re.compile(
    r"""
    (?P<email>(?<![\w.%+-])[A-Za-z0-9][A-Za-z0-9._%+-]{0,63}@[A-Za-z0-9-]{1,63}(?:\.[A-Za-z0-9-]{1,63}){1,8}(?![\w-]))
  | (?P<secret>(?i:(?<![A-Za-z0-9])(?:pass(?:word|wd|phrase)?|pwd|secret|token|(?:api|access|private|secret)?[_-]?key)\b["']?\s{0,3}[=:]\s{0,3}["']?)(?P<value>[A-Za-z0-9+/_.~-]{8,}+))
  | (?P<iban>(?<!\w)[A-Z]{2}[0-9]{2}(?:[ ]?[A-Z0-9]{4}){2,7}(?:[ ]?[A-Z0-9]{1,3})?(?!\w))
  | (?P<date>(?<![\w./-])(?:[0-9]{4}(?P<s1>[-/])[0-9]{1,2}(?P=s1)[0-9]{1,2}|[0-9]{1,2}(?P<s2>[./])[0-9]{1,2}(?P=s2)[0-9]{4})(?![\w/-]|\.[0-9]))
  | (?P<ip>(?<![\w.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?!\w|\.[0-9]))
  | (?P<ssn>(?<![\w-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-]))
  | (?P<nanp>(?<![\w+])(?:\+1[ .-]?)?(?:\([0-9]{3}\)[ .-]?|(?<=\+1)[0-9]{3}[ .-]?|(?<=\+1[ .-])[0-9]{3}[ .-]?|[0-9]{3}[.-])[0-9]{3}[ .-]?[0-9]{4}(?!\w))
  | (?P<phone>(?<![\w+])\+[1-9][0-9]{0,2}(?:[ .-]?\(?[0-9]{1,5}\)?){2,6}(?!\w))
  | (?P<card>(?<![\w.])[0-9](?:[ -]?[0-9]){12,18}(?!\w))
    """,
    re.VERBOSE,
)


def luhn(digits: str) -> int:
    """Check digit that follows ``digits``."""
    total = 0
    for i, d in enumerate(map(int, reversed(digits))):
        total += d if i % 2 else d * 2 - 9 * (d > 4)
    return -total % 10


@lru_cache(maxsize=1)
def days() -> tuple[list[int], list[int]]:
    """Ordinals of 1900-2099: those whose day could be a month, and the others."""
    every = range(datetime.date(1900, 1, 1).toordinal(), datetime.date(2100, 1, 1).toordinal())
    early = [d for d in every if datetime.date.fromordinal(d).day <= 12]
    gone = set(early)
    return early, [d for d in every if d not in gone]


class Pseudonyms:
    """Feistel permutations under one key; ``reveal`` runs them backwards."""

    def __init__(self, key: bytes, reveal: bool = False) -> None:
        self.key, self.reveal = hashlib.blake2b(key, digest_size=32).digest(), reveal

    def _mix(self, kind: str, turn: int, half: int, side: int) -> int:
        """Keyed number of eight bytes more than a half has, so that its remainder is even over the whole half."""
        return int.from_bytes(hashlib.blake2b(b"%s|%d|%d" % (kind.encode(), turn, half), key=self.key, digest_size=side.bit_length() // 8 + 9).digest(), "big")

    def permuted(self, n: int, size: int, kind: str) -> int:
        """Image of ``n`` among 0..size-1. The network works on a square of at least ``size``; what falls outside goes round again."""
        if size < 2:
            return n
        side = isqrt(size - 1) + 1
        kind = f"{kind}|{size}"
        while True:
            a, b = divmod(n, side)
            if self.reveal:
                for turn in reversed(range(ROUNDS)):
                    a, b = b, (a - self._mix(kind, turn, b, side)) % side
            else:
                for turn in range(ROUNDS):
                    a, b = (b + self._mix(kind, turn, a, side)) % side, a
            n = a * side + b
            if n < size:
                return n

    def moved(self, values: np.ndarray, sizes: np.ndarray, kind: str) -> np.ndarray:
        """Image of a run of characters, ``values`` below ``sizes``: each half in turn moves by a stream keyed by the other."""
        halves, half_sizes = np.split(values, [len(values) // 2]), np.split(sizes, [len(values) // 2])
        turns = range(ROUNDS)
        for turn in reversed(turns) if self.reveal else turns:
            own, other = turn % 2, 1 - turn % 2
            tag = b"%s|%d|%d|" % (kind.encode(), turn, len(values))
            stream = hashlib.shake_256(self.key + tag + halves[other].astype("<u2").tobytes()).digest(8 * len(halves[own]))
            step = (np.frombuffer(stream, "<u8") % half_sizes[own].astype(np.uint64)).astype(np.int64)
            halves[own] = (halves[own] + (-step if self.reveal else step)) % half_sizes[own]
        return np.concatenate(halves)

    def letters(self, text: str, kind: str, alphabets: tuple[str, ...]) -> str:
        """Each character that is in one of the alphabets moves inside it; the others stay and belong to the format."""
        place = {c: (k, i) for k, a in enumerate(alphabets) for i, c in enumerate(a)}
        at = [i for i, c in enumerate(text) if c in place]
        kinds, values = [place[text[i]][0] for i in at], [place[text[i]][1] for i in at]
        kind += "|" + "".join(str(place[c][0]) if c in place else c for c in text)
        if len(at) > AS_NUMBER:
            sizes = np.array([len(a) for a in alphabets])[kinds]
            values = self.moved(np.array(values), sizes, kind).tolist()
        else:
            n, size = 0, 1
            for k, v in zip(kinds, values, strict=True):
                n, size = n * len(alphabets[k]) + v, size * len(alphabets[k])
            n = self.permuted(n, size, kind)
            for j in reversed(range(len(at))):
                n, values[j] = divmod(n, len(alphabets[kinds[j]]))
        out = list(text)
        for i, k, v in zip(at, kinds, values, strict=True):
            out[i] = alphabets[k][v]
        return "".join(out)

    def digits(self, text: str, kind: str) -> str:
        return f"{self.permuted(int(text), 10 ** len(text), kind):0{len(text)}d}" if text else ""

    # Each takes a matched value and gives its pseudonym, or None if it doesn't validate.

    def email(self, s: str) -> str | None:
        local, _, domain = s.partition("@")
        return f"{self.letters(local, 'email', (LOWER, UPPER, DIGITS))}@{domain}"

    def secret(self, s: str) -> str | None:
        def kinds(x: str) -> tuple[str, ...]:
            return (HEX,) if not x.strip(HEX) else (HEX.upper(),) if not x.strip(HEX.upper()) else (LOWER, UPPER, DIGITS)

        own = kinds(s)
        new = self.letters(s, "secret", own)
        while kinds(new) != own:
            new = self.letters(new, "secret", own)
        return new

    def card(self, s: str) -> str | None:
        d = re.sub(r"\D", "", s)
        if int(d[-1]) != luhn(d[:-1]) or not int(d):
            return None
        body = d[0] + self.digits(d[1:-1], "card" + d[0])
        return laid(s, body + str(luhn(body)))

    def iban(self, s: str) -> str | None:
        d = s.replace(" ", "")
        if not 15 <= len(d) <= 34 or int("".join(str(int(c, 36)) for c in d[4:] + d[:4])) % 97 != 1:
            return None
        account = self.letters(d[4:], "iban" + d[:2], (DIGITS, UPPER))
        check = 98 - int("".join(str(int(c, 36)) for c in account + d[:2] + "00")) % 97
        return laid(s, f"{d[:2]}{check:02d}{account}")

    def ip(self, s: str) -> str | None:
        parts = s.split(".")
        if any(int(p) > 255 or len(p) > 1 and p[0] == "0" for p in parts) or not 1 <= int(parts[0]) <= 223:
            return None
        n = self.permuted(sum(int(p) << 8 * (3 - i) for i, p in enumerate(parts)) - (1 << 24), 223 << 24, "ip") + (1 << 24)
        return ".".join(str(n >> 8 * (3 - i) & 255) for i in range(4))

    def ssn(self, s: str) -> str | None:
        area, group, serial = map(int, s.split("-"))
        if area in (0, 666) or area > 899 or not group or not serial:
            return None
        n = ((area - 1 - (area > 666)) * 99 + group - 1) * 9999 + serial - 1
        n, serial = divmod(self.permuted(n, 898 * 99 * 9999, "ssn"), 9999)
        area, group = divmod(n, 99)
        return f"{area + 1 + (area >= 665):03d}-{group + 1:02d}-{serial + 1:04d}"

    def nanp(self, s: str) -> str | None:
        d = re.sub(r"\D", "", s)
        code, d = d[:-10], d[-10:]
        if d[0] < "2" or d[3] < "2":  # no area or office has such a number; with its country code it is a phone number all the same
            if not code:
                return None
            d = self.digits(d, "phone1")
            while d[0] >= "2" and d[3] >= "2":
                d = self.digits(d, "phone1")
            return laid(s, code + d)
        n = ((int(d[:3]) - 200) * 800 + int(d[3:6]) - 200) * 10_000 + int(d[6:])
        n, line = divmod(self.permuted(n, 800 * 800 * 10_000, "nanp"), 10_000)
        area, office = divmod(n, 800)
        return laid(s, f"{code}{area + 200}{office + 200}{line:04d}")

    def phone(self, s: str) -> str | None:
        d = re.sub(r"\D", "", s)
        if not 8 <= len(d) <= 15:
            return None
        code = re.match(r"\+([0-9]+)", s)[1]
        code = code if len(code) <= 3 else code[:2]
        return laid(s, code + self.digits(d[len(code) :], "phone" + code))

    def date(self, s: str) -> str | None:
        a, b, c = re.split(r"[./-]", s)
        mark = re.search(r"[./-]", s)[0]
        year_first = len(a) == 4
        month_first = not year_first and mark == "/" and int(b) > 12
        y, m, d = (a, b, c) if year_first else (c, a, b) if month_first else (c, b, a)
        try:
            ordinal = datetime.date(int(y), int(m), int(d)).toordinal()
        except ValueError:
            return None
        early, late = days()
        among = early if int(d) <= 12 else late
        at = bisect_left(among, ordinal)
        if at == len(among) or among[at] != ordinal:
            return None
        new = datetime.date.fromordinal(among[self.permuted(at, len(among), "date" + str(int(d) <= 12))])
        wide = len(m) == len(d) == 2
        m, d = (f"{new.month:02d}", f"{new.day:02d}") if wide else (str(new.month), str(new.day))
        return mark.join((str(new.year), m, d) if year_first else (m, d, str(new.year)) if month_first else (d, m, str(new.year)))

    def replace(self, text: str) -> tuple[str, int]:
        """The text with pseudonyms and their number. Patterns run only around characters that every value has."""
        out, done, n, upto = [], 0, 0, 0
        for anchor in ANCHOR.finditer(text):
            if anchor.start() < upto:
                continue
            lo, hi = max(done, anchor.start() - 80), self._end(text, anchor.start())
            upto = hi
            at = lo
            while (m := FOUND.search(text, at, hi)) is not None:
                kind = m.lastgroup if m.lastgroup not in ("s1", "s2", "value") else "secret" if m["secret"] else "date"
                start, end = m.span("value") if kind == "secret" else m.span()
                new = getattr(self, kind)(text[start:end])
                if new is None and kind in ("card", "phone"):  # it may have run on into the next number
                    for stop in reversed([i for i in range(start + 8, end) if text[i] in " -."]):
                        if (kind == "phone" or sum(map(str.isdigit, text[start:stop])) >= 13) and (new := getattr(self, kind)(text[start:stop])) is not None:
                            end = stop
                            break
                if new is None:
                    at = m.start() + 1
                    continue
                out += (text[done:start], new)
                done, n, at = end, n + 1, end
        return ("".join(out) + text[done:], n) if n else (text, 0)

    @staticmethod
    def _end(text: str, at: int) -> int:
        """End of a stretch: white space, or the text's end, at least 80 characters after the last anchor before it."""
        last, end = at, -1
        while True:
            while (m := ANCHOR.search(text, last + 1, last + 81)) is not None:
                last = m.start()
            if end < last + 80:
                space = SPACE.search(text, min(len(text), last + 80))
                end = space.start() if space else len(text)
            if (m := ANCHOR.search(text, last + 1, end)) is None:
                return end
            last = m.start()


LOWER, UPPER, DIGITS, HEX = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", "0123456789abcdef"


def laid(like: str, value: str) -> str:
    """The letters and digits of ``value`` in the places of those of ``like``."""
    rest = iter(value)
    return "".join(next(rest) if c.isalnum() else c for c in like)


def pseudonymise(docs: DataFrame, key: bytes, text: str = "text", count: str = "n_pii", reveal: bool = False) -> DataFrame:
    """``docs`` with the text replaced and the number of replaced values."""
    kept = [c for c in docs.columns if c.lower() != count.lower()]
    source = docs.select(*(docs[f"`{c}`"] for c in kept))
    schema = T.StructType([*source.schema.fields, T.StructField(count, T.LongType())])
    at = kept.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = Pseudonyms(key, reveal)
        for part in common.pieces(batches, at):
            rows = [(None, 0) if t is None else names.replace(t) for t in part.column(at).to_pylist()]
            columns = list(part.columns)
            columns[at] = pa.array([t for t, _ in rows], pa.string())
            yield pa.RecordBatch.from_arrays([*columns, pa.array([n for _, n in rows], pa.int64())], names=schema.fieldNames())

    return source.mapInArrow(run, schema)


#: For tests and checks only; a caller passes a secret key.
DEMO_KEY = b"blockquant demonstration key"


def op1_pii_feistel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its pseudonymised text."""
    return pseudonymise(common.table(spark, sf_dir, "documents").select("doc_id", "text"), DEMO_KEY)
