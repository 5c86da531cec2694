"""Format-preserving pseudonyms for personal numbers, dates, addresses and secrets in texts.

Each value found is validated (Luhn for cards, mod 97 for IBANs, calendar for dates, octets for
IPv4), split into its fixed parts and its free symbols, and the free symbols are permuted by a keyed
Feistel network over their own radix and length: separators, length, letter case and check
digits stay valid, and equal values get equal pseudonyms in every document. ``restore`` inverts.

Kinds: card (13-19 digits, Luhn), iban, phone (with a country code, or in the 3-3-4 form), ssn (3-2-4),
ipv4, email (local part and host labels before the last two), date (four usual forms, 1800-2199)
and secret (quoted hexadecimal of 32 or more). Numbers that fail validation stay as they are.
Cards and IBANs are sought in runs of groups parted by one blank (cards: or hyphen), as a run can
hold other groups beside the value: at each group the value is that group alone if it is a valid card,
else the longest valid run of whole groups from there, and the search goes on behind it.

Defined cases: null text stays null with no finds; empty texts stay empty; repeated rows are
treated alike; a value that overlaps an earlier kind is left to that kind; other columns of the
table pass through untouched, whatever their names (work columns are never added to it).
"""

from __future__ import annotations

import datetime
import hashlib
import re
from bisect import bisect_left
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from spanweave.llm.batches import slices

#: The default key is for tests; give a secret one in production.
KEY = "demonstration key"
ROUNDS = 10
_FIRST_DAY, _LAST_DAY = datetime.date(1800, 1, 1).toordinal(), datetime.date(2199, 12, 31).toordinal()
KINDS = ("card", "date", "email", "iban", "ipv4", "phone", "secret", "ssn")


class Permuter:
    """Keyed permutations of strings over an alphabet and of integers below a bound."""

    def __init__(self, key: str, inverse: bool = False):
        self.key, self.inverse = hashlib.blake2b(key.encode(), digest_size=32).digest(), inverse

    def _round(self, tweak: str, i: int, value: int) -> int:
        return int.from_bytes(hashlib.blake2b(f"{tweak}:{i}:{value}".encode(), key=self.key, digest_size=16).digest(), "big")

    def number(self, value: int, left: int, right: int, tweak: str) -> int:
        """Permutes 0 <= value < left * right."""
        a, b = divmod(value, right)
        rounds = range(ROUNDS)
        for i in reversed(rounds) if self.inverse else rounds:
            sign = -1 if self.inverse else 1
            if i % 2 == 0:
                a = (a + sign * self._round(tweak, i, b)) % left
            else:
                b = (b + sign * self._round(tweak, i, a)) % right
        return a * right + b

    def below(self, value: int, bound: int, tweak: str) -> int:
        """Permutes 0 <= value < bound by walking the cycle of a slightly larger domain."""
        left = int(bound**0.5) + 1
        right = -(-bound // left)
        value = self.number(value, left, right, tweak)
        while value >= bound:
            value = self.number(value, left, right, tweak)
        return value

    def symbols(self, text: str, alphabet: str, tweak: str) -> str:
        n, radix = len(text), len(alphabet)
        if not n:
            return text
        value = 0
        for ch in text:
            value = value * radix + alphabet.index(ch)
        value = self.number(value, radix ** (n // 2), radix ** (n - n // 2), f"{tweak}:{radix}:{n}")
        out = []
        for _ in range(n):
            value, d = divmod(value, radix)
            out.append(alphabet[d])
        return "".join(reversed(out))


_DIGITS, _LETTERS, _HEX = "0123456789", "abcdefghijklmnopqrstuvwxyz", "0123456789abcdef"


def luhn_sum(digits: str) -> int:
    total = 0
    for i, ch in enumerate(reversed(digits)):
        d = int(ch) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10


def _fill(shape: str, free: str, wanted: Callable[[str], bool]) -> str:
    """``shape`` with its wanted characters replaced by those of ``free`` in order."""
    it = iter(free)
    return "".join(next(it) if wanted(ch) else ch for ch in shape)


def _is_card(digits: str) -> bool:
    return 13 <= len(digits) <= 19 and not luhn_sum(digits) and len(set(digits)) > 1


def _card(p: Permuter, s: str) -> str:
    digits = re.sub(r"\D", "", s)
    body = p.symbols(digits[:-1], _DIGITS, "card")
    return _fill(s, body + str(-luhn_sum(body + "0") % 10), str.isdigit)


def _mod97(s: str) -> int:
    return int("".join(str(int(ch, 36)) for ch in s)) % 97


def _is_iban(flat: str) -> bool:
    return 15 <= len(flat) <= 34 and _mod97(flat[4:] + flat[:4]) == 1


def _iban(p: Permuter, s: str) -> str:
    flat = s.replace(" ", "")
    body = _mixed(p, flat[4:], "iban")
    check = 98 - _mod97(body + flat[:2] + "00")
    return _fill(s, f"{flat[:2]}{check:02d}{body}", lambda ch: ch != " ")


def _mixed(p: Permuter, s: str, tweak: str) -> str:
    """Digits among digits, letters among letters in their case; everything else stays."""
    digits = p.symbols("".join(ch for ch in s if ch in _DIGITS), _DIGITS, tweak)
    low = s.lower()
    letters = iter(p.symbols("".join(ch for ch in low if ch in _LETTERS), _LETTERS, tweak))
    figures = iter(digits)
    return "".join(next(figures) if ch in _DIGITS else (x.upper() if raw.isupper() else x) if ch in _LETTERS and (x := next(letters)) else raw for ch, raw in zip(low, s))


def _phone(p: Permuter, s: str) -> str | None:
    start = re.match(r"\+\d{1,3}(?=[ .(-])|\+\d{2}|", s).end()
    digits = re.sub(r"\D", "", s[start:])
    return s[:start] + _fill(s[start:], p.symbols(digits, _DIGITS, "phone"), str.isdigit) if 6 <= len(digits) <= 14 else None


def _ssn(p: Permuter, s: str) -> str | None:
    digits, never = s.replace("-", ""), ("000", "666", "9")
    if digits.startswith(never):
        return None
    digits = p.symbols(digits, _DIGITS, "ssn")
    while digits.startswith(never):
        digits = p.symbols(digits, _DIGITS, "ssn")
    return _fill(s, digits, str.isdigit)


def _ipv4(p: Permuter, s: str) -> str | None:
    parts = [int(x) for x in s.split(".")]
    if max(parts) > 255:
        return None
    value = p.number(int.from_bytes(bytes(parts), "big"), 1 << 16, 1 << 16, "ipv4")
    return ".".join(map(str, value.to_bytes(4, "big")))


def _email(p: Permuter, s: str) -> str | None:
    name, _, host = s.partition("@")
    labels = host.split(".")
    return f"{_mixed(p, name, 'email')}@{'.'.join([*(_mixed(p, x, 'host') for x in labels[:-2]), *labels[-2:]])}"


def _date(p: Permuter, s: str) -> str | None:
    a, sep, b, c = re.match(r"(\d+)(\D)(\d+)\D(\d+)", s).groups()
    year, month, day = (a, b, c) if len(a) == 4 else (c, a, b) if sep == "/" and int(b) > 12 else (c, b, a)
    order = "ymd" if len(a) == 4 else "mdy" if (month, day) == (a, b) and sep == "/" else "dmy"
    try:
        at = datetime.date(int(year), int(month), int(day)).toordinal() - _FIRST_DAY
    except ValueError:
        return None
    span = _LAST_DAY - _FIRST_DAY + 1
    if not 0 <= at < span:
        return None
    while True:  # month before day reads back so only with a day above 12
        at = p.below(at, span, "date")
        d = datetime.date.fromordinal(at + _FIRST_DAY)
        if order != "mdy" or d.day > 12:
            break
    parts = {"y": f"{d.year:04d}", "m": f"{d.month:02d}", "d": f"{d.day:02d}"}
    return sep.join(parts[x] for x in order)


def _secret(p: Permuter, s: str) -> str | None:
    out = p.symbols(s.lower(), _HEX, "secret")
    return out.upper() if s.isupper() else out


_GROUP, _IBAN = re.compile(r"\d+"), re.compile(r"[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?")
_IBAN_RUN, _IBAN_CUT = re.compile(r"[A-Z0-9]+(?: [A-Z0-9]+)*"), re.compile(r" |(?![A-Za-z0-9 ])|$")


def _free(start: int, end: int, taken: list[tuple[int, int]]) -> bool:
    return not any(start < e and b < end for b, e in taken)


def _card_end(text: str, at: int, taken: list[tuple[int, int]]) -> int | None:
    """The end of the card that begins with the group at ``at``, if there is one."""
    digits, best, first = "", None, at
    while (m := _GROUP.match(text, at)) and len(digits) + len(m.group()) <= 19 and _free(m.start(), m.end(), taken):
        if at > first and _is_card(m.group()):
            break
        digits += m.group()
        if _is_card(digits):
            best = m.end()
            if at == first:
                break
        if text[m.end() : m.end() + 1] not in (" ", "-"):
            break
        at = m.end() + 1
    return best


def _iban_end(text: str, at: int, taken: list[tuple[int, int]]) -> int | None:
    """The end of the longest valid IBAN of whole groups from ``at``, if there is one."""
    if not (m := _IBAN_RUN.match(text, at, at + 48)):
        return None
    run = m.end()
    ends = [m.start() for m in _IBAN_CUT.finditer(text, at, run + 1) if at < m.start() <= run]
    for end in reversed(ends):
        if _IBAN.fullmatch(text, at, end) and _is_iban(text[at:end].replace(" ", "")) and _free(at, end, taken):
            return end
    return None


#: Kinds sought group by group: their pattern finds the groups that can begin a value, the function its end.
_ENDS = {"card": _card_end, "iban": _iban_end}
#: No value of these kinds is longer with its blanks.
_REACH = 64


def _groups(text: str, kind: str, starts: re.Pattern, taken: list[tuple[int, int]]) -> list[tuple[int, int | None]]:
    """(start, end of the value that begins there or None) of the groups, going on behind each value."""
    seen, at = [], 0
    while m := starts.search(text, at):
        seen.append((m.start(), _ENDS[kind](text, m.start(), taken)))
        at = seen[-1][1] or m.start() + 1
    return seen


#: kind, what must be in the text at all, pattern, pseudonym (None: the value is not valid)
_FINDERS: tuple[tuple[str, str, re.Pattern, Callable[[Permuter, str], str | None]], ...] = (
    ("email", "@", re.compile(r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}@(?:[A-Za-z0-9-]{1,63}\.){1,8}[A-Za-z]{2,24}"), _email),
    ("secret", '"', re.compile(r'(?<=")(?:[0-9a-f]{32,128}|[0-9A-F]{32,128})(?=")'), _secret),
    ("iban", "", re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?=(?: ?[A-Z0-9]{4}){2})"), _iban),
    ("ipv4", ".", re.compile(r"(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?!\.?\d)"), _ipv4),
    ("date", "", re.compile(r"(?<![\d./-])(?:\d{4}-\d{2}-\d{2}|\d{4}/\d{2}/\d{2}|\d{2}/\d{2}/\d{4}|\d{2}[.-]\d{2}[.-]\d{4})(?![./-]?\d)"), _date),
    ("card", "", re.compile(r"(?:(?<![\d+.-])|(?<=\d-))\d(?=(?:[ -]?\d){12})"), _card),
    ("phone", "", re.compile(r"(?<![\w+])(?:\+\d{1,3}[ .-]?(?:\(\d{1,4}\)|\d{1,4})(?:[ .-]?\d{2,4}){2,4}|\(\d{3}\) ?\d{3}[ .-]\d{4}|\d{3}[.-]\d{3}[.-]\d{4})(?!\d)"), _phone),
    ("ssn", "-", re.compile(r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"), _ssn),
)
_DIGIT = re.compile(r"\d")


def finds(text: str | None, permuter: Permuter) -> list[tuple[int, int, str, str]]:
    """(start, end, kind, pseudonym) of the values in a text, in order and without overlaps.

    A pseudonym after which a group nearby would be read otherwise is permuted again, so that the
    same values are found when it is restored (values are then taken in the opposite order)."""
    if not text or not ("@" in text or _DIGIT.search(text) or '"' in text):
        return []
    out: list[tuple[int, int, str, str]] = []
    taken: list[tuple[int, int]] = []
    watched = []
    for kind, needs, pattern, pseudonym in _FINDERS:
        if needs and needs not in text:
            continue
        if kind in _ENDS:
            if seen := _groups(text, kind, pattern, taken):
                watched.append((_ENDS[kind], seen, taken))
                out += [(s, e, kind, pseudonym(permuter, text[s:e])) for s, e in seen if e]
        else:
            for m in pattern.finditer(text):
                if _free(m.start(), m.end(), taken) and (new := pseudonym(permuter, m.group())) is not None:
                    out.append((m.start(), m.end(), kind, new))
        taken = sorted((x[0], x[1]) for x in out)
    if watched:
        again, now = {f[0]: f[3] for f in _FINDERS}, text
        for i in reversed(range(len(out))) if permuter.inverse else range(len(out)):
            s, e, kind, new = out[i]
            near = [(end_of, seen[j], by) for end_of, seen, by in watched for j in range(bisect_left(seen, (s - _REACH,)), bisect_left(seen, (e,)))]
            if len(new) != e - s:  # an address, which no group reaches into
                continue
            now = now[:s] + new + now[e:]
            while not all(end_of(now, a, by) == b for end_of, (a, b), by in near):
                new = again[kind](permuter, new)
                now = now[:s] + new + now[e:]
            out[i] = (s, e, kind, new)
    return sorted(out)


def pseudonymize(text: str | None, permuter: Permuter) -> tuple[str | None, list[tuple[int, int, str, str]]]:
    got = finds(text, permuter)
    if not got:
        return text, got
    parts, at = [], 0
    for start, end, _, new in got:
        parts += [text[at:start], new]
        at = end
    return "".join([*parts, text[at:]]), got


@lru_cache(maxsize=8)
def _permuter(key: str, inverse: bool) -> Permuter:
    return Permuter(key, inverse)


def rewrite(docs: DataFrame, *, key: str = KEY, inverse: bool = False, text: str = "text") -> DataFrame:
    """The table with ``text`` pseudonymised (``inverse``: restored); every column and row stays."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, text):
            new = [pseudonymize(t, _permuter(key, inverse))[0] for t in part.column(text).to_pylist()]
            at = part.schema.get_field_index(text)
            yield part.set_column(at, part.schema.field(at), pa.array(new, part.schema.field(at).type))

    return docs.mapInArrow(run, docs.schema)


def report(docs: DataFrame, *, key: str = KEY) -> DataFrame:
    """doc_id, pseudonymised text, n_<kind> of each document."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches):
            done = [pseudonymize(t, _permuter(key, False)) for t in part.column("text").to_pylist()]
            counts = [pa.array([sum(f[2] == k for f in got) for _, got in done], pa.int64()) for k in KINDS]
            yield pa.record_batch([part.column("doc_id"), pa.array([t for t, _ in done], pa.string()), *counts], names=["doc_id", "text", *(f"n_{k}" for k in KINDS)])

    schema = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), *(T.StructField(f"n_{k}", T.LongType()) for k in KINDS)])
    return docs.select("doc_id", "text").mapInArrow(run, schema)
