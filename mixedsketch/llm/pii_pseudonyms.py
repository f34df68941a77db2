"""Format-preserving pseudonyms for personal data.

Each validated value is brought to one form (a date to its day number, a phone
number to its digits, an address to its number), permuted among the values of
its kind by a keyed Feistel network, and written in the format it was found in:
a card number stays a card number with the same check, a date a date, an
address an address.  One key gives one permutation, so equal values stay equal
across all documents and spellings and different ones stay different, without
any lookup table and without moving a row.  (Where a format can be read day
first or month first, two different days may be written alike.)
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from datetime import date
from functools import lru_cache
from ipaddress import IPv6Address

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel
from .workspace import ship

ROUNDS = 8
KEY_SETTING = "spark.mixedsketch.pii.key"  # of the session; the registered queries fall back on DEMO_KEY
DEMO_KEY = b"mixedsketch demonstration key: replace in production"

#: Alphabets a character is permuted within; any other character stays.
ALPHABETS = [
    "0123456789",
    "abcdefghijklmnopqrstuvwxyz",
    "ABCDEFGHIJKLMNOPQRSTUVWXYZ",
    "àáâãäåæçèéêëìíîïðñòóôõöøùúûüýþÿ",
    "ÀÁÂÃÄÅÆÇÈÉÊËÌÍÎÏÐÑÒÓÔÕÖØÙÚÛÜÝÞ",
]
HEX_LOWER, HEX_UPPER = "0123456789abcdef", "0123456789ABCDEF"
_OF = {c: a for a in ALPHABETS for c in a}


class Feistel:
    """A keyed permutation of 0..n-1, by a balanced network on bits and cycle walking."""

    def __init__(self, key: bytes, tweak: str):
        self.seed = hashlib.blake2b(tweak.encode(), key=hashlib.blake2b(key).digest()[:64]).digest()

    def _once(self, x: int, half: int) -> int:
        mask = (1 << half) - 1
        left, right = x >> half, x & mask
        size = -(-half // 8)
        for r in range(ROUNDS):
            f = hashlib.shake_256(self.seed + bytes([r]) + right.to_bytes(size, "big")).digest(size)
            left, right = right, left ^ (int.from_bytes(f, "big") & mask)
        return left << half | right

    def permute(self, x: int, n: int, allowed: Callable[[int], bool] | None = None) -> int:
        """Image of ``x`` among the values below ``n`` that are ``allowed`` (``x`` must be one)."""
        if n <= 1:
            return x
        half = max(1, -(-(n - 1).bit_length() // 2))
        while True:
            x = self._once(x, half)
            if x < n and (allowed is None or allowed(x)):
                return x


def _digits_of(text: str, alphabets: list[str]) -> tuple[int, int]:
    value, n = 0, 1
    for c, a in zip(text, alphabets, strict=True):
        value, n = value * len(a) + a.index(c), n * len(a)
    return value, n


def _text_of(value: int, alphabets: list[str]) -> str:
    out = []
    for a in reversed(alphabets):
        value, d = divmod(value, len(a))
        out.append(a[d])
    return "".join(reversed(out))


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def iban_valid(text: str) -> bool:
    moved = text[4:] + text[:4]
    return int("".join(str(int(c, 36)) for c in moved)) % 97 == 1


def ssn_valid(digits: str) -> bool:
    return digits[:3] not in ("000", "666") and digits[0] != "9" and digits[3:5] != "00" and digits[5:] != "0000"


#: Days of the years people write most are permuted among themselves, all others likewise.
_FIRST_DAY, _LAST_DAY = date(1900, 1, 1).toordinal(), date(2099, 12, 31).toordinal()
_ALL_DAYS = date.max.toordinal()

#: Months as they are written, and country calling codes of one and two digits (others have three).
MONTHS = "January February March April May June July August September October November December".split()
SHORT_MONTHS = "Jan Feb Mar Apr May Jun Jul Aug Sep Oct Nov Dec".split()
CODES = frozenset("1 7 20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split())
_MONTH = "(?i:" + "|".join(MONTHS + ["Sept", *SHORT_MONTHS]) + ")"


def _code(digits: str) -> int:
    """Length of the country calling code that an international number begins with."""
    return next((n for n in (1, 2) if digits[:n] in CODES), min(3, len(digits) - 1))


def _month_of(name: str) -> int:
    return next(i + 1 for i, m in enumerate(SHORT_MONTHS) if name[:3].lower() == m.lower())


class Pseudonymiser:
    """Finds values and gives their pseudonyms under one key."""

    #: kind, pattern; earlier kinds win where several match at one place
    PATTERNS = [
        ("secret", r"(?i:(?<!\w)(?:token|secret|password|passwd|api[_-]?key|access[_-]?key)[ \t]*[:=][ \t]*[\"']?)(?P<secret>[A-Za-z0-9+/_=-]{8,})"),
        ("token", r"(?<![\w-])(?:AKIA|ASIA|gh[oprsu]_|github_pat_|glpat-|sk-|sk_live_|sk_test_|AIza|xox[abprs]-)(?P<token>[A-Za-z0-9][A-Za-z0-9_-]{14,})(?![\w-])"),
        ("email", r"(?<![\w.+%-])(?P<email>[\w+%-]+(?:\.[\w+%-]+)*@[A-Za-z0-9](?:[A-Za-z0-9-]*[A-Za-z0-9])?(?:\.[A-Za-z0-9](?:[A-Za-z0-9-]*[A-Za-z0-9])?)*\.[A-Za-z]{2,24})(?![\w@])"),
        ("iban", r"(?<!\w)(?P<iban>[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?)(?!\w)"),
        ("iso_date", r"(?<![\w./-])(?P<iso_date>\d{4}-\d{2}-\d{2})(?=T\d{2}:|(?![\w-]))"),
        ("month_date", rf"(?<![\w./-])(?P<month_date>\d{{1,2}}(?:st|nd|rd|th|\.)?[ -](?:of )?{_MONTH}\.?,?[ -]\d{{4}}|{_MONTH}\.? \d{{1,2}}(?:st|nd|rd|th)?,? \d{{4}})(?![\w-])"),
        ("date", r"(?<![\w./-])(?P<date>\d{1,2}(?P<mark>[./-])\d{1,2}(?P=mark)\d{4})(?![\w-])"),
        ("ip", r"(?<![\w.])(?P<ip>(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d))(?!\w|\.\d)"),
        ("ipv6", r"(?<![\w:.])(?P<ipv6>(?:[0-9A-Fa-f]{0,4}:){2,7}[0-9A-Fa-f]{0,4})(?![\w:])"),
        ("ssn", r"(?<![\w-])(?P<ssn>\d{3}-\d{2}-\d{4})(?![\w-])"),
        ("phone", r"(?<![\w+])(?P<phone>\+1[ .-]?(?:\(\d{3}\)[ .-]?|\d{3}[ .-]?)\d{3}[ .-]?\d{4}|\+\d{1,3}[ -]?(?:\(\d{1,4}\)[ -]?)?\d{2,4}(?:[ -]?\d{2,4}){1,4}|\(\d{3}\) ?\d{3}[ .-]\d{4}|\d{3}[.-]\d{3}[.-]\d{4}|[2-9]\d{2}[2-9]\d{6})(?![\w-]|\.\d)"),
        ("account", r"(?<![\w.])(?P<account>\d(?:[ -]?\d){12,18})(?!\w|[.-]\d)"),
    ]
    SCAN = re.compile("|".join(p for _, p in PATTERNS))
    #: a line without any of these cannot hold a value, and no value goes over a line's end
    SIEVE = r"[0-9@]|(?i:token|secret|passw|key)|AKIA|ASIA|gh[oprsu]_|_pat_|glpat-|sk[-_]|AIza|xox"
    SPOT, WORDS = re.compile("[0-9@]"), ("token", "secret", "passw", "key", "akia", "asia", "gho_", "ghp_", "ghr_", "ghs_", "ghu_", "_pat_", "glpat-", "sk-", "sk_", "aiza", "xox")

    def __init__(self, key: bytes):
        self.key = key
        self.image = lru_cache(maxsize=200_000)(self._image)
        self.networks: dict[str, Feistel] = {}

    def network(self, tweak: str) -> Feistel:
        if tweak not in self.networks:
            if len(self.networks) > 10_000:
                self.networks.clear()
            self.networks[tweak] = Feistel(self.key, tweak)
        return self.networks[tweak]

    def _string(self, tweak: str, text: str, alphabets: dict[str, str] = _OF, allowed: Callable[[str], bool] | None = None) -> str:
        """Permute the characters that have an alphabet; all others keep their places."""
        spots = [i for i, c in enumerate(text) if c in alphabets]
        kinds = [alphabets[text[i]] for i in spots]
        if not spots:
            return text
        value, n = _digits_of("".join(text[i] for i in spots), kinds)
        tweak = f"{tweak}:" + "".join(str(len(k)) + "," for k in kinds)
        image = self.network(tweak).permute(value, n, (lambda v: allowed(_text_of(v, kinds))) if allowed else None)
        out = list(text)
        for i, c in zip(spots, _text_of(image, kinds), strict=True):
            out[i] = c
        return "".join(out)

    def _image(self, kind: str, text: str) -> str | None:
        """The pseudonym, or None where the value is not valid for its kind."""
        digits = re.sub(r"\D", "", text)
        if kind in ("secret", "token"):
            for alphabet in (HEX_LOWER, HEX_UPPER):
                if all(c in alphabet for c in text):
                    return self._string(kind, text, dict.fromkeys(alphabet, alphabet))
            return self._string(kind, text)
        if kind == "email":  # capitals are a matter of spelling
            head, _, top = text.rpartition(".")
            small = head.lower() if len(head.lower()) == len(head) else head
            image = self._string(kind, small)
            return "".join(c.upper() if o != s and len(c.upper()) == 1 else c for c, o, s in zip(image, head, small, strict=True)) + "." + top
        if kind == "iban":
            compact = text.replace(" ", "")
            if not 15 <= len(compact) <= 34 or not iban_valid(compact):
                return None
            body = self._string(kind + compact[:2], compact[4:])
            check = 98 - int("".join(str(int(c, 36)) for c in body + compact[:2] + "00")) % 97
            fresh = iter(f"{compact[:2]}{check:02d}{body}")
            return "".join(c if c == " " else next(fresh) for c in text)
        if kind in ("iso_date", "date", "month_date"):
            return self._date(kind, text)
        if kind == "ipv6":
            try:
                value = int(IPv6Address(text))
            except ValueError:
                return None
            if len([g for g in text.split(":") if g]) < 3 or not digits:
                return None
            image = IPv6Address(self.network("ipv6").permute(value, 1 << 128))
            out = image.exploded if len(text) == 39 else str(image)
            return out.upper() if text.upper() == text else out
        if kind == "ip":
            value = 0
            for part in text.split("."):
                value = value << 8 | int(part)
            image = self.network("ip").permute(value, 1 << 32)
            return ".".join(str(image >> s & 255) for s in (24, 16, 8, 0))
        if kind == "ssn":
            return self._string(kind, text, allowed=ssn_valid) if ssn_valid(digits) else None
        if kind == "phone":
            if not 7 <= len(digits) <= 15:
                return None
            skip = _code(digits) if text.startswith("+") else 0
            code = digits[:skip] or ("1" if len(digits) == 10 else "")  # ten digits are the same number as those after +1
            value, n = int(digits[skip:]), 10 ** (len(digits) - skip)
            image = iter(digits[:skip] + str(self.network(f"phone:{code}:{n}").permute(value, n)).zfill(len(digits) - skip))
            return "".join(next(image) if c.isdigit() else c for c in text)
        if luhn(digits):
            return self._string(kind, text, allowed=luhn)
        return None  # no valid number as a whole; the scan goes on inside

    def _day(self, day: int) -> date:
        usual = _FIRST_DAY <= day <= _LAST_DAY
        return date.fromordinal(self.network("date").permute(day, _ALL_DAYS + 1, lambda v: v > 0 and (_FIRST_DAY <= v <= _LAST_DAY) == usual))

    def _date(self, kind: str, text: str) -> str | None:
        """The date of the image day, in the order, padding and names of ``text``; None if it is no date."""
        if kind == "month_date":
            name = re.search(r"[A-Za-z]{3,}", re.sub(r"(?<=\d)(?:st|nd|rd|th)|\bof\b", "", text)).group()
            numbers = [int(n) for n in re.findall(r"\d+", text)]
            try:
                image = self._day(date(numbers[1], _month_of(name), numbers[0]).toordinal())
            except ValueError:
                return None
            fresh = (MONTHS if len(name) > 4 or name.lower() in ("june", "july") else SHORT_MONTHS)[image.month - 1]
            fresh = fresh.upper() if name.isupper() else fresh.lower() if name.islower() else fresh
            out = text.replace(name, "\0", 1)
            day = str(image.day).zfill(2 if re.search(r"(?<!\d)0\d(?!\d)", text) else 1)
            ends = "th" if 10 < image.day < 14 else {1: "st", 2: "nd", 3: "rd"}.get(image.day % 10, "th")
            out = re.sub(r"(?<!\d)\d{1,2}(st|nd|rd|th)?(?!\d)", lambda m: day + (ends if m.group(1) else ""), out, count=1)
            out = re.sub(r"(?<!\d)\d{4}(?!\d)", f"{image.year:04d}", out, count=1)
            return out.replace("\0", fresh)
        parts = re.findall(r"\d+", text)
        orders = [(0, 1, 2)] if kind == "iso_date" else [(2, 1, 0), (2, 0, 1)]  # day first, then month first
        for y, m, d in orders:
            try:
                day = date(int(parts[y]), int(parts[m]), int(parts[d])).toordinal()
            except ValueError:
                continue
            image = self._day(day)
            padded = len(parts[m]) == len(parts[d]) == 2  # one digit where there may be two: fields are not padded
            fields = {y: f"{image.year:04d}", m: str(image.month).zfill(2 if padded else 1), d: str(image.day).zfill(2 if padded else 1)}
            fresh = iter([fields[i] for i in range(3)])
            return re.sub(r"\d+", lambda _: next(fresh), text)
        return None

    def rewrite(self, text: str) -> tuple[str, list[str]]:
        """The text with pseudonyms, and the kinds replaced in order."""
        kinds: list[str] = []
        low = text.lower()
        worded = any(w in low for w in self.WORDS)
        lines = text.split("\n")
        for i, line in enumerate(lines):
            if self.SPOT.search(line) or worded and any(w in line.lower() for w in self.WORDS):
                lines[i] = self._line(line, kinds)
        return "\n".join(lines), kinds

    def _line(self, line: str, kinds: list[str]) -> str:
        out, done, at = [], 0, 0
        while match := self.SCAN.search(line, at):
            kind = next(k for k, _ in self.PATTERNS if match.start(k) >= 0)
            lo, hi = match.span(kind)
            image = self.image(kind, line[lo:hi])
            if image is None:  # another value may begin inside
                at = match.start() + 1
                continue
            kinds.append(kind)
            out += [line[done:lo], image]
            done = at = hi
        return "".join(out) + line[done:]


_ready: dict[bytes, Pseudonymiser] = {}


def _pseudonymise(key: bytes, text_col: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if key not in _ready:
            _ready[key] = Pseudonymiser(key)
        swap = _ready[key]
        for batch in batches:
            text = batch.column(text_col)
            may = pc.fill_null(pc.match_substring_regex(text, Pseudonymiser.SIEVE), False)
            found: list = [None] * batch.num_rows
            rows = may.to_numpy(zero_copy_only=False).nonzero()[0]
            fresh = []
            for i, value in zip(rows, text.filter(may).to_pylist(), strict=True):
                new, kinds = swap.rewrite(value)
                fresh.append(new)
                found[i] = kinds or None
            out = pc.replace_with_mask(text, may, pa.array(fresh, type=text.type)) if fresh else text
            columns = [out if n == text_col else batch.column(n) for n in batch.schema.names]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(found, pa.list_(pa.string()))], names=[*batch.schema.names, "pii_kinds"])

    return run


def session_key(spark: SparkSession) -> bytes:
    """The key that the session names, or the public one for demonstrations."""
    return spark.conf.get(KEY_SETTING, "").encode() or DEMO_KEY


def pseudonymise(docs: DataFrame, key: bytes, text_col: str = "text") -> DataFrame:
    """All rows and columns of ``docs`` with pseudonyms in ``text_col``, plus ``pii_kinds`` (null where nothing was replaced).

    Kinds: secret, token, email, iban, iso_date, month_date, date, ip, ipv6, ssn, phone, account.  Values
    that fail their check (a date that is none, an IBAN or a run of 13 to 19
    digits with a wrong check) are no such values and stay.  Null texts
    stay null, empty ones empty; repeated rows change alike.  A column that is
    called pii_kinds already is replaced.
    """
    ship(docs.sparkSession)
    docs = docs.drop("pii_kinds")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.mapInArrow(kernel.tidy(_pseudonymise(key, text_col)), f"{schema}, pii_kinds array<string>")


def op1_pii_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents`` with pseudonyms."""
    out = pseudonymise(spark.read.parquet(f"{sf_dir}/documents.parquet"), session_key(spark))
    kinds = F.coalesce("pii_kinds", F.array().cast("array<string>"))
    return out.select("doc_id", "text", "lang", "source", F.char_length("text").cast("long").alias("n_chars"), F.size(kinds).cast("long").alias("n_replaced"), F.array_join(F.array_sort(F.array_distinct(kinds)), ",").alias("kinds"))
